"""Secret spans: three fixed patterns, and strings that a compressor primed with code cannot shorten.

Novelty: a candidate is a run of 16 or more token characters that holds a letter and a digit, in a
sensitive context: a line that names something sensitive, the line after it, or a block between the BEGIN
and END lines of a private key (where any run counts). Its marginal size is what it adds to a zstandard frame of its
surroundings (256 characters on either side without other such runs, after a stretch of plain words, so that the compressor knows
how frequent letters are even where a text is short), compressed with a dictionary: words of code, and the
identifiers that most documents of the corpus have. At 0.9 compressed bytes a character or more, and 3
bits of entropy over its characters, it is reported as kind `novel` unless a pattern's span covers it.

The identifiers are counted over all documents (words of 4 to 32 letters and underscores, once a document);
the IDENTIFIERS most frequent ones, ties by name, are the dictionary, the PLAIN next ones the plain words (a
fixed list where there are fewer): a bounded size, whatever the corpus's.

Cases: null text is empty, which has no span; repeated rows give repeated rows; an empty table gives
none. Only doc_id and text are read. Spans are code points of the whole match, end exclusive.
"""

from __future__ import annotations

import math
import re
from collections import Counter
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import blocks, table, text_of, workers_can_import

#: The base kinds in their order, each with its least length (of group 2 where there is one).
KINDS = (
    ("assign", r"""((?i:password|passwd|secret|token|api_?key))["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", 8),
    ("access", r"AKIA[A-Z0-9]+", 16),
    ("hex", r"[0-9a-f]+", 32),
)
#: Words that make a line sensitive.
SENSITIVE = r"(?i)secret|token|passw|pwd|credential|auth|bearer|private|api[_-]?key|access[_-]?key|signature|session|AKIA"
RUN = r"[A-Za-z0-9+/_=-]{16,}"
KEY_BLOCK = r"-----BEGIN [A-Z ]*PRIVATE KEY-----(.*?)(?:-----END|\Z)"
IDENTIFIER, IDENTIFIERS, PLAIN = r"[A-Za-z_]{4,32}", 2000, 80
#: Plain words for a corpus that has too few.
PLAIN_WORDS = (
    "with they this have from word what were when your said there which their will about other many then them these some would make like into time look more write "
    "number people than first water been call long down come made part over new sound take only little work know place year live back give most very after thing our just"
)
CODE_WORDS = (
    "def return import from class self None True False lambda yield raise except finally async await public private protected static final void "
    "int long double float boolean string String const let var function new this null undefined export default interface extends implements package "
    "select insert update delete where group order by having join table index values config settings environment variable export PATH HOME USER "
    "username user_name password passwd secret token api_key apikey access_key secret_key client_id client_secret authorization Bearer Basic "
    "http https www com org net localhost example test development production staging database connection host port timeout retry "
    "get_user_by_id set_value load_config read_file write_file parse_json to_string from_string create_session close_connection handle_request "
    "abcdefghijklmnopqrstuvwxyz ABCDEFGHIJKLMNOPQRSTUVWXYZ 0123456789 00000000 xxxxxxxx changeme example_key your_token_here placeholder"
)
LEAST_RATIO, LEAST_BITS, AROUND = 0.9, 3.0, 256
_compiled = [(k, re.compile(p if k != "hex" else r"[0-9a-f]{32,}", re.ASCII), n) for k, p, n in KINDS]
_sensitive, _run, _block = re.compile(SENSITIVE, re.ASCII), re.compile(RUN, re.ASCII), re.compile(KEY_BLOCK, re.ASCII | re.DOTALL)


def base_spans(text: str) -> list[tuple[int, int, int]]:
    """(start, order of the kind, end). A hex run of 32 or more is the whole run, so shorter ones needn't be looked at."""
    out = []
    for order, (_, pattern, least) in enumerate(_compiled):
        for m in pattern.finditer(text):
            if len(m[m.lastindex or 0]) >= least:
                out.append((m.start(), order, m.end()))
    return sorted(out)


def bits(s: str) -> float:
    n = len(s)
    return -sum(c / n * math.log2(c / n) for c in Counter(s).values())


def identifiers(docs: DataFrame, most: int = IDENTIFIERS + PLAIN) -> list[str]:
    """The identifiers that most documents have, most frequent first."""
    words = F.explode(F.array_distinct(F.regexp_extract_all("text", F.lit(IDENTIFIER), 0))).alias("w")
    counts = docs.select(words).groupBy("w").agg(F.count("*").alias("n")).where("n > 1")
    return [r["w"] for r in counts.orderBy(F.col("n").desc(), "w").limit(most).collect()]


class Novelty:
    """Marginal compressed size against the surroundings, under a dictionary of code words and identifiers."""

    def __init__(self, words: list[str] | None = None) -> None:
        import zstandard

        # what is likeliest stands last, nearest to the text
        words = words or []
        text = " ".join([*reversed(words[:IDENTIFIERS]), CODE_WORDS])
        plain = words[IDENTIFIERS:]
        self.plain = (" ".join(plain) if len(plain) == PLAIN else PLAIN_WORDS) + "\n"
        self.dict = zstandard.ZstdCompressionDict(text.encode(), dict_type=zstandard.DICT_TYPE_RAWCONTENT)
        self.dict.precompute_compress(level=3)
        self.z = zstandard.ZstdCompressor(dict_data=self.dict, write_content_size=False)

    def size(self, text: str) -> int:
        return len(self.z.compress((self.plain + text).encode()))

    def ratio(self, text: str, start: int, end: int) -> float:
        near = _run.sub(" ", text[max(0, start - AROUND) : start]) + _run.sub(" ", text[end : end + AROUND])
        return (self.size(near + text[start:end]) - self.size(near)) / (end - start)


def contexts(text: str) -> list[tuple[int, int, bool]]:
    """(start, end, whole) of sensitive stretches in order, apart from each other; whole: inside a private key's block."""
    blocks_ = [(*m.span(1), True) for m in _block.finditer(text)] if "PRIVATE KEY" in text else []
    out: list[tuple[int, int, bool]] = []
    for word in _sensitive.finditer(text):
        begin, end = text.rfind("\n", 0, word.start()) + 1, text.find("\n", word.end())
        if end >= 0:  # the next line belongs to it
            end = text.find("\n", end + 1)
        end = len(text) if end < 0 else end
        if out and begin <= out[-1][1]:
            out[-1] = (out[-1][0], max(end, out[-1][1]), False)
        else:
            out.append((begin, end, False))
    return blocks_ + out


def novel_spans(text: str, base: list[tuple[int, int, int]], novelty: Novelty) -> list[tuple[int, int]]:
    out: set[tuple[int, int]] = set()
    for begin, end, whole in contexts(text):
        for m in _run.finditer(text, begin, end):
            s, e = m.span()
            run = m[0]
            if (s, e) in out or any(a < e and s < b for a, _, b in base):
                continue
            if not whole and not (any(c.isdigit() for c in run) and any(c.isalpha() for c in run)):
                continue
            if bits(run) >= LEAST_BITS and novelty.ratio(text, s, e) >= LEAST_RATIO:
                out.add((s, e))
    return sorted(out)


def find_secrets(docs: DataFrame, words: list[str] | None = None) -> DataFrame:
    """doc_id and spans: kind, start and end of all spans in order. words: the identifiers, learned from docs if not given."""
    workers_can_import(docs.sparkSession)
    words = identifiers(docs) if words is None else words

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        novelty = Novelty(words)
        names = [k for k, _, _ in KINDS]
        for batch in blocks(batches):
            rows = []
            for d, text in zip(batch.column("doc_id").to_pylist(), batch.column("text").to_pylist(), strict=True):
                base = base_spans(text)
                extra = [(s, 3, e) for s, e in novel_spans(text, base, novelty)]
                rows.append((d, [{"kind": ([*names, "novel"])[k], "start": s, "end": e} for s, k, e in sorted([*base, *extra])]))
            kind = pa.list_(pa.struct([("kind", pa.string()), ("start", pa.int64()), ("end", pa.int64())]))
            yield pa.RecordBatch.from_arrays([pa.array([r[0] for r in rows], pa.int64()), pa.array([r[1] for r in rows], kind)], names=["doc_id", "spans"])

    return text_of(docs).mapInArrow(run, "doc_id long, spans array<struct<kind: string, start: long, end: long>>")


def op7_secret_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = find_secrets(table(spark, sf_dir, "documents"))

    def of(kind: str):
        return F.size(F.filter("spans", lambda s: s["kind"] == kind)).cast("long")

    def line(spans):
        return F.array_join(F.transform(spans, lambda s: F.concat_ws(":", s["kind"], s["start"].cast("string"), s["end"].cast("string"))), ",")

    base = F.filter("spans", lambda s: s["kind"] != "novel")
    return found.select("doc_id", of("assign").alias("n_assign"), of("access").alias("n_access"), of("hex").alias("n_hex"), F.sha2(line(base), 256).alias("base_sha256"), line(F.col("spans")).alias("spans"), of("novel").alias("n_novel"))


def op7_base_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The part of op7_secret_scan that SQL can say."""
    return op7_secret_scan(spark, sf_dir).select("doc_id", "n_assign", "n_access", "n_hex")


_PATTERNS = {k: (p.replace("'", "''"), n) for k, p, n in KINDS}
BASE_COUNTS = f"""SELECT doc_id, len(list_filter(regexp_extract_all(t, '{_PATTERNS["assign"][0]}', 2), lambda x: length(x) >= 8))::BIGINT AS n_assign,
  len(list_filter(regexp_extract_all(t, '{_PATTERNS["access"][0]}'), lambda x: length(x) >= 16))::BIGINT AS n_access,
  len(list_filter(regexp_extract_all(t, '{_PATTERNS["hex"][0]}'), lambda x: length(x) >= 32))::BIGINT AS n_hex FROM (SELECT doc_id, coalesce(text, '') AS t FROM documents) d"""
