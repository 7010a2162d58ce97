"""Token ids of whole texts by the tokenizers library, with word pieces encoded once a worker."""

from __future__ import annotations

import json
import re

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

from .common import as_bytes

#: The pattern by which a tokenizer file with such steps lower-cases and splits.
LOWER_SPLIT = r"'s|'t|'re|'ve|'m|'ll|'d|[\p{L}]+|[\p{N}]|[^\s\p{L}\p{N}]+"
CONTRACTION = re.compile(rb"'(?:[stmd]|re|ve|ll)")
#: Classes of characters: the space, other white space, letters, numbers, the rest.
BLANK, SPACE, LETTER, NUMBER, REST = range(5)


def _classes() -> tuple[np.ndarray, np.ndarray]:
    """The class of each byte below 128, and of the second byte after 0xC2 and 0xC3.

    Fixed values: among the first 256 code points, on which every Unicode version and library agree, letters
    are A-Z, a-z, U+AA, U+B5, U+BA and U+C0 to U+FF but for U+D7 and U+F7; numbers 0-9, U+B2, U+B3, U+B9, U+BC
    to U+BE; white space U+9 to U+D, the space, U+85 and U+A0."""
    kind = np.full(256, REST, np.uint8)
    kind[[*range(0x41, 0x5B), *range(0x61, 0x7B), 0xAA, 0xB5, 0xBA, *range(0xC0, 0xD7), *range(0xD8, 0xF7), *range(0xF8, 0x100)]] = LETTER
    kind[[*range(0x30, 0x3A), 0xB2, 0xB3, 0xB9, 0xBC, 0xBD, 0xBE]] = NUMBER
    kind[[*range(0x09, 0x0E), 0x85, 0xA0]] = SPACE
    kind[0x20] = BLANK
    return kind[:128], kind[128:]


ONE, TWO = _classes()
_loaded: dict[tuple[str, int], WordIds] = {}


class Numbers(dict):
    """Gives a new key the next number and notes it."""

    def __init__(self) -> None:
        super().__init__()
        self.new: list[str] = []

    def __missing__(self, key: str) -> int:
        self.new.append(key)
        self[key] = n = len(self)
        return n


def steps_of(spec: dict) -> str | None:
    """'bytes' or 'lower' for the two known kinds of a tokenizer file's steps, None for others, whose texts are encoded whole."""
    kinds = lambda part, many: [x["type"] for x in (part or {}).get(many, [part] if part else [])]
    before, split = spec.get("normalizer"), spec.get("pre_tokenizer") or {}
    steps = split.get("pretokenizers", [split])
    last = steps[-1]
    if spec["model"]["type"] != "BPE" or last.get("type") != "ByteLevel" or last.get("add_prefix_space"):
        return None
    ends = spec["model"].get("end_of_word_suffix") or None
    if before is None and len(steps) == 1 and last.get("use_regex") and ends is None:
        return "bytes"
    same = kinds(before, "normalizers") == ["NFC", "Replace", "Lowercase"] and before["normalizers"][1]["pattern"] == {"Regex": r"\s+"} and before["normalizers"][1]["content"] == " "
    cut = len(steps) == 2 and steps[0].get("type") == "Split" and steps[0].get("pattern") == {"Regex": LOWER_SPLIT} and steps[0].get("behavior") == "Removed" and steps[0].get("invert")
    return "lower" if same and cut and not last.get("use_regex") and ends == "</w>" else None


def piece_starts(raw: np.ndarray, off: np.ndarray, lower: bool) -> tuple[np.ndarray, np.ndarray]:
    """(starts of pieces, texts they are right for): where the pre-tokenizer cuts texts of the first 256 code points.

    Pieces are runs of letters, of numbers (lower: single ones) or of the rest, a blank before one belonging to
    it (not lower), and contractions. A text that has other code points, or (not lower) two white spaces in a row,
    whose cut depends on what follows, is not right."""
    lead = (raw & 0xC0) != 0x80
    kind = np.where(raw < 128, ONE[raw & 127], REST)
    two = np.flatnonzero((raw == 0xC2) | (raw == 0xC3))
    value = (raw[two + 1] & 0x3F) | ((raw[two] & 1) << 6)
    kind[two] = kind[two + 1] = TWO[value]
    if lower:
        kind[kind == BLANK] = SPACE
    before = np.concatenate([[np.uint8(255)], kind[:-1]]) if len(kind) else kind
    before[off[:-1][np.diff(off) > 0]] = 255
    new = lead & (kind != before)
    if lower:
        new |= lead & (kind == NUMBER)
    else:
        new &= before != BLANK
    wrong = (raw >= 0xC4) if lower else (raw >= 0xC4) | (lead & (kind <= SPACE) & (before <= SPACE))
    bad = np.concatenate([[0], np.cumsum(wrong)])
    for m in CONTRACTION.finditer(raw.tobytes()):
        a, e = m.span()
        if new[a] and not (before[a + 1 : e] == 255).any():
            new[a + 1] = False
            if e < len(new) and kind[e] == LETTER:
                new[e] = True
    new[off[:-1][np.diff(off) > 0]] = True
    return np.flatnonzero(new), bad[off[1:]] == bad[off[:-1]]


class WordIds:
    """ids(texts): one array of ids a text, the same as the tokenizer's own with add_special_tokens=False.

    The pre-tokenizer's pieces don't depend on what surrounds them, so each distinct piece of a block is
    looked up once, and encoded once as long as it is remembered; at most about `most` pieces are. Texts with
    code points beyond the first 256, with an added token's literal content or with white space that
    doesn't cut simply are encoded whole, as are all texts of a tokenizer whose file states unknown steps."""

    def __init__(self, path: str, most: int = 250_000) -> None:
        from tokenizers import Tokenizer

        self.tok = Tokenizer.from_file(path)
        with open(path, encoding="utf-8") as f:
            spec = json.load(f)
        self.kind = steps_of(spec)
        self.lower = self.kind == "lower"
        self.added = [t["content"].encode() for t in spec.get("added_tokens") or []]
        # whether an id ends a lower-cased word, or starts a word after a space (which stands as U+0120)
        self.edge = np.zeros(self.tok.get_vocab_size() + 1, bool)
        for token, i in spec["model"].get("vocab", {}).items():
            self.edge[i] = token.endswith("</w>") if self.lower else token[:1] == "\u0120"
        self.most = most
        self.clear()

    def clear(self) -> None:
        self.index = Numbers()
        self.flat, self.size = np.zeros(0, np.uint32), np.zeros(0, np.int64)
        self.first = np.zeros(0, np.int64)

    def encoded(self, words: list[str]) -> tuple[np.ndarray, np.ndarray]:
        """The ids of words, one after another, and how many each has.

        Plain words are encoded many at a time: between spaces they stay pieces of their own, and ids tell
        where one ends (lower-cased) or starts (else)."""
        size = np.zeros(len(words), np.int64)
        plain = [i for i, w in enumerate(words) if (w if self.lower else w[1:]).isalpha() and (self.lower or w[0] == " ")]
        other = sorted(set(range(len(words))).difference(plain))
        groups = [plain[i : i + 500] for i in range(0, len(plain), 500)]
        texts = [(" " if self.lower else "").join([words[i] for i in g]) for g in groups]
        ids = []
        for g, e in zip(groups, self.tok.encode_batch_fast(texts, add_special_tokens=False), strict=True):
            got = np.array(e.ids, np.uint32)
            edge = np.flatnonzero(self.edge[got])
            size[g] = np.diff(edge, prepend=-1) if self.lower else np.diff(edge, append=len(got))
            ids.append(got)
        for i, e in zip(other, self.tok.encode_batch_fast([words[i] for i in other], add_special_tokens=False), strict=True):
            size[i] = len(e.ids)
            ids.append(np.array(e.ids, np.uint32))
        flat = np.concatenate(ids) if ids else np.zeros(0, np.uint32)
        order = np.array([*plain, *other], np.int64)
        place = np.empty(len(words), np.int64)
        place[order] = np.cumsum(size[order]) - size[order]
        return flat[np.repeat(place - (np.cumsum(size) - size), size) + np.arange(len(flat))], size

    def learn(self) -> None:
        if self.index.new:
            flat, size = self.encoded(self.index.new)
            self.first = np.concatenate([self.first, len(self.flat) + np.cumsum(size) - size])
            self.flat, self.size = np.concatenate([self.flat, flat]), np.concatenate([self.size, size])
            self.index.new = []

    def ids(self, texts: pa.Array | list[str]) -> list[np.ndarray]:
        if len(self.index) > self.most:
            self.clear()
        texts = pa.array(texts, pa.string()) if isinstance(texts, list) else texts
        out: list[np.ndarray | None] = [None] * len(texts)
        simple = self._simple(texts, out) if self.kind and len(texts) else np.zeros(len(texts), bool)
        whole = np.flatnonzero(~simple)
        for i, e in zip(whole.tolist(), self.tok.encode_batch_fast(texts.take(pa.array(whole)).to_pylist(), add_special_tokens=False), strict=True):
            out[i] = np.array(e.ids, dtype=np.uint32)
        return out

    def _simple(self, texts: pa.Array, out: list) -> np.ndarray:
        """Fills in the ids of texts whose pieces are looked up; which these are."""
        plain, off = as_bytes(texts)
        block = plain.tobytes()
        raw = plain
        if self.lower:
            raw, low = as_bytes(pc.utf8_lower(texts))
            if (low != off).any():  # lower-casing beyond the first 256 code points may change lengths
                fine = np.array([len(t.encode()) == n and max(t, default="") < "\u0100" for t, n in zip(texts.to_pylist(), np.diff(off), strict=True)])
                raw, _ = as_bytes(pc.utf8_lower(pc.if_else(pa.array(fine), texts, "")))
                off_all, off = off, np.concatenate([[0], np.cumsum(np.where(fine, np.diff(off), 0))])
            else:
                fine = np.ones(len(texts), bool)
        else:
            fine = np.ones(len(texts), bool)
        starts, right = piece_starts(raw, off, self.lower)
        right &= fine
        for a in self.added:
            at = block.find(a)
            while at >= 0:
                right[np.searchsorted(off_all if self.lower and not fine.all() else off, at, side="right") - 1] = False
                at = block.find(a, at + 1)
        ends = pa.py_buffer(np.append(starts, len(raw)).astype(np.int32))
        pieces = pa.StringArray.from_buffers(len(starts), ends, pa.py_buffer(np.ascontiguousarray(raw))).dictionary_encode()
        words = pieces.dictionary.to_pylist()
        number = np.fromiter(map(self.index.__getitem__, words), np.int64, len(words))
        self.learn()
        at = number[np.asarray(pieces.indices)]
        size = self.size[at]
        stop = np.cumsum(size)
        flat = self.flat[np.repeat(self.first[at] - (stop - size), size) + np.arange(int(size.sum()))]
        border = np.concatenate([[0], stop])[np.searchsorted(starts, off)]
        for i in np.flatnonzero(right).tolist():
            out[i] = flat[border[i] : border[i + 1]]
        return right


def tokenizer(path: str) -> WordIds:
    import os

    key = (path, os.getpid())
    if key not in _loaded:
        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        _loaded[key] = WordIds(path)
    return _loaded[key]


def vocabulary(name: str) -> str:
    import public_tokenizers

    return public_tokenizers.path(name)
