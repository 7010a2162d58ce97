"""Lossless WebP (VP8L) in numpy: a decoder for the whole format and an encoder for sample arrays.

The decoder reads all prefix codes of all groups, back-references and the colour cache, and inverts
the predictor, cross-colour, subtract-green and palette transforms. Streams of one code group
without a colour cache, as the encoder writes them, are decoded by a table look-up at every bit
position at once, followed by a walk from code to code.
"""

from __future__ import annotations

import struct

import numpy as np

#: Fixed values of the format: the order of code-length codes, and the places near a pixel that short distance codes name.
LENGTH_ORDER = (17, 18, 0, 1, 2, 3, 4, 5, 16, 6, 7, 8, 9, 10, 11, 12, 13, 14, 15)
NEAR = (
    (0, 1), (1, 0), (1, 1), (-1, 1), (0, 2), (2, 0), (1, 2), (-1, 2), (2, 1), (-2, 1), (2, 2), (-2, 2), (0, 3), (3, 0), (1, 3), (-1, 3), (3, 1), (-3, 1), (2, 3), (-2, 3),
    (3, 2), (-3, 2), (0, 4), (4, 0), (1, 4), (-1, 4), (4, 1), (-4, 1), (3, 3), (-3, 3), (2, 4), (-2, 4), (4, 2), (-4, 2), (0, 5), (3, 4), (-3, 4), (4, 3), (-4, 3), (5, 0),
    (1, 5), (-1, 5), (5, 1), (-5, 1), (2, 5), (-2, 5), (5, 2), (-5, 2), (4, 4), (-4, 4), (3, 5), (-3, 5), (5, 3), (-5, 3), (0, 6), (6, 0), (1, 6), (-1, 6), (6, 1), (-6, 1),
    (2, 6), (-2, 6), (6, 2), (-6, 2), (4, 5), (-4, 5), (5, 4), (-5, 4), (3, 6), (-3, 6), (6, 3), (-6, 3), (0, 7), (7, 0), (1, 7), (-1, 7), (5, 5), (-5, 5), (7, 1), (-7, 1),
    (4, 6), (-4, 6), (6, 4), (-6, 4), (2, 7), (-2, 7), (7, 2), (-7, 2), (3, 7), (-3, 7), (7, 3), (-7, 3), (5, 6), (-5, 6), (6, 5), (-6, 5), (8, 0), (4, 7), (-4, 7), (7, 4),
    (-7, 4), (8, 1), (8, 2), (6, 6), (-6, 6), (8, 3), (5, 7), (-5, 7), (7, 5), (-7, 5), (8, 4), (6, 7), (-6, 7), (7, 6), (-7, 6), (8, 5), (7, 7), (-7, 7), (8, 6), (8, 7),
)
PREDICTOR, CROSS_COLOUR, SUBTRACT_GREEN, PALETTE = range(4)
BLACK = 0xFF000000
MAX_SIDE, MAX_COPY = 16384, 4096
_REV8 = np.array([int(f"{i:08b}"[::-1], 2) for i in range(256)], np.uint32)


def reversed_bits(code: np.ndarray, size: np.ndarray) -> np.ndarray:
    whole = (_REV8[code & 255] << 8) | _REV8[code >> 8]
    return whole >> (16 - size.astype(np.uint32))


def canonical(lengths: np.ndarray) -> np.ndarray:
    """Each symbol's code, bit-reversed as the stream holds it; symbols without a code get 0."""
    at = np.lexsort((np.arange(len(lengths)), lengths))
    at = at[lengths[at] > 0]
    size = lengths[at].astype(np.int64)
    top = int(size.max(initial=1))
    left = np.cumsum(1 << (top - size)) - (1 << (top - size))
    out = np.zeros(len(lengths), np.uint32)
    out[at] = reversed_bits((left >> (top - size)).astype(np.uint32), size)
    return out


class Code:
    """A prefix code as a table over the next `top` bits: symbols and their lengths."""

    __slots__ = ("only", "sizes", "symbols", "top")

    def __init__(self, lengths: np.ndarray) -> None:
        used = np.flatnonzero(lengths)
        self.only = int(used[0]) if len(used) == 1 else 0 if not len(used) else None
        if self.only is not None:
            self.top, self.symbols, self.sizes = 0, np.array([self.only], np.int32), np.zeros(1, np.uint8)
            return
        size = lengths[used]
        if int((1 << (15 - size.astype(np.int64))).sum()) != 1 << 15:
            raise ValueError("prefix code is not complete")
        self.top = int(size.max())
        codes = canonical(lengths)[used].tolist()
        self.symbols, self.sizes = np.empty(1 << self.top, np.int32), np.empty(1 << self.top, np.uint8)
        for s, c, n in zip(used.tolist(), codes, size.tolist(), strict=True):
            self.symbols[c :: 1 << n] = s
            self.sizes[c :: 1 << n] = n


class Bits:
    def __init__(self, data: bytes) -> None:
        self.data, self.pos = data + b"\0" * 8, 0

    def read(self, n: int) -> int:
        at = self.pos >> 3
        x = int.from_bytes(self.data[at : at + 8], "little") >> (self.pos & 7)
        self.pos += n
        return x & ((1 << n) - 1)

    def symbol(self, code: Code) -> int:
        if code.only is not None:
            return code.only
        at = self.pos >> 3
        x = (int.from_bytes(self.data[at : at + 4], "little") >> (self.pos & 7)) & ((1 << code.top) - 1)
        self.pos += int(code.sizes[x])
        return int(code.symbols[x])

    def amount(self, prefix: int) -> int:
        """The value of a length or distance prefix and its extra bits."""
        if prefix < 4:
            return prefix + 1
        extra = (prefix - 2) >> 1
        return ((2 + (prefix & 1)) << extra) + self.read(extra) + 1


def read_code(b: Bits, alphabet: int) -> Code:
    lengths = np.zeros(alphabet, np.uint8)
    if b.read(1):
        two, wide = b.read(1), b.read(1)
        lengths[b.read(8 if wide else 1)] = 1
        if two:
            lengths[b.read(8)] = 1
        return Code(lengths)
    first = np.zeros(19, np.uint8)
    for k in LENGTH_ORDER[: 4 + b.read(4)]:
        first[k] = b.read(3)
    code = Code(first)
    left = alphabet if not b.read(1) else 2 + b.read(2 + 2 * b.read(3))
    at, last = 0, 8
    while at < alphabet and left:
        left -= 1
        k = b.symbol(code)
        if k < 16:
            lengths[at] = k
            at, last = at + 1, k or last
        else:
            n = 3 + b.read(2) if k == 16 else 3 + b.read(3) if k == 17 else 11 + b.read(7)
            if k == 16:
                lengths[at : at + n] = last
            at += n
    if at > alphabet:
        raise ValueError("code lengths run over the alphabet")
    return Code(lengths)


def distance(code: int, width: int) -> int:
    if code > 120:
        return code - 120
    x, y = NEAR[code - 1]
    return max(1, x + y * width)


def read_pixels(b: Bits, width: int, height: int, main: bool) -> np.ndarray:
    """An entropy-coded image as ARGB numbers (uint32, flat)."""
    cache_bits = b.read(4) if b.read(1) else 0
    groups_at, bits = None, 0
    if main and b.read(1):
        bits = b.read(3) + 2
        across = (width + (1 << bits) - 1) >> bits
        meta = read_pixels(b, across, (height + (1 << bits) - 1) >> bits, False)
        groups_at = ((meta >> 8) & 0xFFFF).tolist()
    n_groups = 1 + (max(groups_at) if groups_at else 0)
    cache_size = (1 << cache_bits) if cache_bits else 0
    groups = [[read_code(b, n) for n in (280 + cache_size, 256, 256, 256, 40)] for _ in range(n_groups)]
    if n_groups == 1 and not cache_size:
        return fast_pixels(b, width, height, groups[0])
    out = [0] * (width * height)
    cache = [0] * cache_size
    at, total = 0, width * height

    def put(i: int, v: int) -> None:
        out[i] = v
        if cache_size:
            cache[((0x1E35A7BD * v) & 0xFFFFFFFF) >> (32 - cache_bits)] = v

    while at < total:
        g = groups[groups_at[(at // width >> bits) * ((width + (1 << bits) - 1) >> bits) + (at % width >> bits)]] if groups_at else groups[0]
        s = b.symbol(g[0])
        if s < 256:
            red, blue, alpha = b.symbol(g[1]), b.symbol(g[2]), b.symbol(g[3])
            put(at, alpha << 24 | red << 16 | s << 8 | blue)
            at += 1
        elif s < 280:
            n = b.amount(s - 256)
            d = distance(b.amount(b.symbol(g[4])), width)
            if d > at or at + n > total:
                raise ValueError("back-reference out of the image")
            for i in range(at, at + n):
                put(i, out[i - d])
            at += n
        else:
            put(at, cache[s - 280])
            at += 1
    return np.array(out, np.uint32)


def fast_pixels(b: Bits, width: int, height: int, codes: list[Code]) -> np.ndarray:
    total = width * height
    start = b.pos >> 3
    raw = np.frombuffer(b.data, np.uint8)[start:].astype(np.uint32)
    raw = np.append(raw, np.zeros(3, np.uint32))
    words = raw[:-3] | raw[1:-2] << 8 | raw[2:-1] << 16
    top = max(c.top for c in codes[:4])
    looks = ((words[:, None] >> np.arange(8, dtype=np.uint32)) & np.uint32((1 << top) - 1)).ravel()
    n = len(looks)
    first = looks & np.uint32((1 << codes[0].top) - 1) if codes[0].top < top else looks
    # a place's next one; far below zero after a code that isn't a literal
    step = codes[0].sizes.astype(np.int32)
    step[codes[0].symbols >= 256] = -(1 << 30)
    after = step[first]
    after += np.arange(n, dtype=np.int32)
    mids = []
    for c in codes[1:4]:
        mids.append(None if c.only is not None else after)
        if c.only is None:
            x = looks[np.clip(after, 0, n - 1)] & np.uint32((1 << c.top) - 1)
            after = np.where(after < 0, after, after + c.sizes[x])
    follow = memoryview(np.ascontiguousarray(after, np.int32))
    p, at = b.pos - 8 * start, 0
    starts, firsts, copies = [], [], []
    if codes[0].only is not None and codes[0].only < 256 and all(c.only is not None for c in codes[1:4]):
        firsts.append((0, 0, total))
        starts = np.full(total, p, np.int64)
        at = total
    else:
        walk: list[int] = []
        add = walk.append
        while True:
            begin = len(walk)
            for _ in range(total - at):
                q = follow[p]
                if q < 0:
                    break
                add(p)
                p = q
            firsts.append((at, begin, len(walk) - begin))
            at += len(walk) - begin
            if at == total:
                break
            b.pos = p + 8 * start
            k = b.amount(b.symbol(codes[0]) - 256)
            d = distance(b.amount(b.symbol(codes[4])), width)
            if d > at or at + k > total:
                raise ValueError("back-reference out of the image")
            copies.append((at, k, d))
            at += k
            p = b.pos - 8 * start
        starts = np.fromiter(walk, np.int64, len(walk))
    value = (codes[0].symbols[first[starts]].astype(np.uint32) & 255) << 8
    for c, mid, shift in zip(codes[1:4], mids, (16, 0, 24), strict=True):
        if mid is None:
            value |= np.uint32(c.only << shift)
        else:
            value |= c.symbols[looks[mid[starts]] & np.uint32((1 << c.top) - 1)].astype(np.uint32) << np.uint32(shift)
    out = np.empty(total, np.uint32)
    for to, a, k in firsts:
        out[to : to + k] = value[a : a + k]
    for to, k, d in copies:
        if d >= k:
            out[to : to + k] = out[to - d : to - d + k]
        else:
            out[to : to + k] = np.resize(out[to - d : to], k)
    b.pos = p + 8 * start
    return out


def _channels(v: np.ndarray) -> np.ndarray:
    return np.ascontiguousarray(v, "<u4").view(np.uint8).reshape(*v.shape, 4)


def _numbers(c: np.ndarray) -> np.ndarray:
    return np.ascontiguousarray(c, np.uint8).view("<u4").reshape(c.shape[:-1])


def predict(mode: int, left, top, right, corner):
    """One pixel's prediction from its neighbours (sequences of four channel values)."""
    mean = lambda a, b: [(x + y) >> 1 for x, y in zip(a, b, strict=True)]
    clamp = lambda x: 0 if x < 0 else 255 if x > 255 else x
    if mode == 0 or mode > 13:
        return [0, 0, 0, 255]
    if mode <= 4:
        return (left, top, right, corner)[mode - 1]
    if mode == 5:
        return mean(mean(left, right), top)
    if mode <= 9:
        return mean(*((left, corner), (left, top), (corner, top), (top, right))[mode - 6])
    if mode == 10:
        return mean(mean(left, corner), mean(top, right))
    if mode == 11:
        to_left = sum(abs(t - c) for t, c in zip(top, corner, strict=True))
        to_top = sum(abs(x - c) for x, c in zip(left, corner, strict=True))
        return left if to_left < to_top else top
    if mode == 12:
        return [clamp(x + t - c) for x, t, c in zip(left, top, corner, strict=True)]
    return [clamp(m + int((m - c) / 2)) for m, c in zip(mean(left, top), corner, strict=True)]


def run_predictor(v: np.ndarray, modes: np.ndarray, bits: int, forward: bool = False) -> np.ndarray:
    """Adds (or, forward, subtracts) each pixel's prediction; v is (height, width) ARGB."""
    h, w = v.shape
    src = _channels(v).astype(int).tolist()
    done = [[None] * w for _ in range(h)]
    kinds = (((modes >> 8) & 255) & 15).tolist()
    for y in range(h):
        for x in range(w):
            ref = src if forward else done
            if x == 0 and y == 0:
                p = [0, 0, 0, 255]
            elif y == 0:
                p = ref[0][x - 1]
            elif x == 0:
                p = ref[y - 1][0]
            else:
                right = ref[y - 1][x + 1] if x + 1 < w else ref[y][0]
                p = predict(kinds[y >> bits][x >> bits], ref[y][x - 1], ref[y - 1][x], right, ref[y - 1][x - 1])
            done[y][x] = [(a - b if forward else a + b) & 255 for a, b in zip(src[y][x], p, strict=True)]
    return _numbers(np.array(done, np.uint8))


def run_cross_colour(v: np.ndarray, parts: np.ndarray, bits: int, forward: bool = False) -> np.ndarray:
    h, w = v.shape
    grid = np.repeat(np.repeat(parts, 1 << bits, 0), 1 << bits, 1)[:h, :w]
    to_red, to_blue, red_to_blue = (((grid >> s) & 255).astype(np.uint8).view(np.int8).astype(np.int32) for s in (0, 8, 16))
    c = _channels(v).copy()
    signed = lambda x: x.astype(np.uint8).view(np.int8).astype(np.int32)
    green, red, blue = signed(c[..., 1]), c[..., 2].astype(np.int32), c[..., 0].astype(np.int32)
    new_red = (red - ((to_red * green) >> 5) if forward else red + ((to_red * green) >> 5)) & 255
    plain_red = red if forward else new_red
    change = ((to_blue * green) >> 5) + ((red_to_blue * signed(np.ascontiguousarray(plain_red.astype(np.uint8)))) >> 5)
    c[..., 2], c[..., 0] = new_red, (blue - change if forward else blue + change) & 255
    return _numbers(c)


def subtract_green(v: np.ndarray, forward: bool = False) -> np.ndarray:
    c = _channels(v).copy()
    for k in (0, 2):
        c[..., k] = c[..., k] - c[..., 1] if forward else c[..., k] + c[..., 1]
    return _numbers(c)


def packing_bits(colours: int) -> int:
    return 3 if colours <= 2 else 2 if colours <= 4 else 1 if colours <= 16 else 0


def unpack_palette(v: np.ndarray, table: np.ndarray, width: int) -> np.ndarray:
    k = packing_bits(len(table))
    index = (v >> 8) & 255
    if k:
        each = 8 >> k
        index = ((index[:, :, None] >> (each * np.arange(1 << k, dtype=np.uint32))) & ((1 << each) - 1)).reshape(len(v), -1)[:, :width]
    wide = np.zeros(256, np.uint32)
    wide[: len(table)] = table
    return wide[index]


def decode(data: bytes) -> np.ndarray:
    """ARGB pixels (height, width, uint32) of one lossless WebP file."""
    if data[:4] != b"RIFF" or data[8:16] != b"WEBPVP8L" or data[20] != 0x2F:
        raise ValueError("not a lossless WebP file")
    b = Bits(data[21 : 20 + struct.unpack("<I", data[16:20])[0]])
    width, height = b.read(14) + 1, b.read(14) + 1
    alpha = b.read(1)
    if b.read(3):
        raise ValueError("unknown version")
    steps, now = [], width
    while b.read(1):
        kind = b.read(2)
        if kind in (PREDICTOR, CROSS_COLOUR):
            bits = b.read(3) + 2
            w, h = (now + (1 << bits) - 1) >> bits, (height + (1 << bits) - 1) >> bits
            steps.append((kind, read_pixels(b, w, h, False).reshape(h, w), bits, now))
        elif kind == PALETTE:
            n = b.read(8) + 1
            table = _numbers(np.cumsum(_channels(read_pixels(b, n, 1, False)), axis=0, dtype=np.uint8))
            steps.append((kind, table, 0, now))
            k = packing_bits(n)
            now = (now + (1 << k) - 1) >> k
        else:
            steps.append((kind, None, 0, now))
    v = read_pixels(b, now, height, True).reshape(height, now)
    for kind, part, bits, w in reversed(steps):
        if kind == PREDICTOR:
            v = run_predictor(v, part, bits)
        elif kind == CROSS_COLOUR:
            v = run_cross_colour(v, part, bits)
        elif kind == SUBTRACT_GREEN:
            v = subtract_green(v)
        else:
            v = unpack_palette(v, part, w)
    return v if alpha else v | np.uint32(BLACK)


def huffman_lengths(counts: np.ndarray, most: int) -> np.ndarray:
    """Code lengths up to `most` for the symbols with counts, by merging two sorted queues."""
    out = np.zeros(len(counts), np.uint8)
    used = np.flatnonzero(counts)
    if len(used) < 2:
        out[used] = 1
        return out
    weights = counts[used].astype(np.int64)
    while True:
        order = np.argsort(weights, kind="stable")
        leaf, n = weights[order].tolist(), len(used)
        up, inner = [0] * (2 * n - 1), []
        i = j = 0
        for new in range(n, 2 * n - 1):
            total = 0
            for _ in range(2):
                if i < n and (j >= len(inner) or leaf[i] <= inner[j]):
                    total += leaf[i]
                    up[i] = new
                    i += 1
                else:
                    total += inner[j]
                    up[n + j] = new
                    j += 1
            inner.append(total)
        depth = [0] * (2 * n - 1)
        for k in range(2 * n - 3, -1, -1):
            depth[k] = depth[up[k]] + 1
        if max(depth[:n]) <= most:
            out[used[order]] = depth[:n]
            return out
        weights = (weights + 1) // 2 + int(weights.sum() >> (most + 2)) + 1


class Fields:
    """Numbers of given bit lengths, packed from the lowest bit on."""

    def __init__(self) -> None:
        self.values: list[np.ndarray] = []
        self.sizes: list[np.ndarray] = []
        self.few: list[tuple[int, int]] = []

    def put(self, value: int, size: int) -> None:
        if size:
            self.few.append((value, size))

    def flush(self) -> None:
        if self.few:
            v, s = zip(*self.few, strict=True)
            self.values.append(np.array(v, np.uint64))
            self.sizes.append(np.array(s, np.int64))
            self.few = []

    def extend(self, values: np.ndarray, sizes: np.ndarray) -> None:
        self.flush()
        self.values.append(values.astype(np.uint64))
        self.sizes.append(sizes.astype(np.int64))

    def bytes(self) -> bytes:
        self.flush()
        v, s = np.concatenate(self.values), np.concatenate(self.sizes)
        end = np.cumsum(s)
        at = end - s
        total = int(end[-1])
        word, off = at >> 6, (at & 63).astype(np.uint64)
        out = np.zeros((total >> 6) + 2, np.uint64)
        first = np.flatnonzero(np.diff(word, prepend=-1))
        out[word[first]] |= np.bitwise_or.reduceat(v << off, first)
        over = np.flatnonzero(off.astype(np.int64) + s > 64)
        out[word[over] + 1] |= v[over] >> (np.uint64(64) - off[over])
        return out.view(np.uint8)[: (total + 7) >> 3].tobytes()


def write_code(f: Fields, lengths: np.ndarray) -> None:
    used = np.flatnonzero(lengths).tolist()
    if len(used) <= 2 and all(s < 256 for s in used):
        used = used or [0]
        f.put(1, 1)
        f.put(len(used) - 1, 1)
        f.put(1, 1)
        for s in used:
            f.put(s, 8)
        return
    f.put(0, 1)
    tokens: list[tuple[int, int, int]] = []
    flat, i, n = lengths.tolist(), 0, used[-1] + 1
    while i < n:
        k = flat[i]
        if k:
            tokens.append((k, 0, 0))
            i += 1
            continue
        run = 1
        while i + run < n and not flat[i + run]:
            run += 1
        i += run
        while run >= 11:
            take = min(run, 138)
            tokens.append((18, take - 11, 7))
            run -= take
        if run >= 3:
            tokens.append((17, run - 3, 3))
            run = 0
        tokens += [(0, 0, 0)] * run
    # the number of tokens ends the list, so the alphabet's empty rest needs none
    counts = np.bincount([t[0] for t in tokens], minlength=19)
    first = huffman_lengths(counts, 7)
    single = np.count_nonzero(first) == 1
    code = [0] * 19 if single else canonical(first).tolist()
    size = first.tolist()
    last = max(i for i, k in enumerate(LENGTH_ORDER) if size[k]) + 1
    last = max(last, 4)
    f.put(last - 4, 4)
    for k in LENGTH_ORDER[:last]:
        f.put(size[k], 3)
    left = max(len(tokens), 2)
    nbits = max(2, (left - 2).bit_length())
    nbits += nbits & 1
    f.put(1, 1)
    f.put((nbits - 2) >> 1, 3)
    f.put(left - 2, nbits)
    tokens += [(0, 0, 0)] * (left - len(tokens))
    for k, extra, n in tokens:
        if not single:
            f.put(code[k], size[k])
        f.put(extra, n)


def prefix_of(value: int) -> tuple[int, int, int]:
    """(prefix, extra bits' value, their number) of a length or distance from 1 up."""
    v = value - 1
    if v < 4:
        return v, 0, 0
    extra = v.bit_length() - 2
    return 2 * extra + 2 + ((v >> extra) & 1), v & ((1 << extra) - 1), extra


def write_image(f: Fields, v: np.ndarray, copies: list[tuple[int, int, int]], main: bool, cache_bits: int = 0) -> None:
    """Entropy-codes ARGB numbers (flat); copies: (start, length up to MAX_COPY, distance) in order."""
    f.put(cache_bits > 0, 1)
    if cache_bits:
        f.put(cache_bits, 4)
    if main:
        f.put(0, 1)
    c = _channels(v)
    size = 1 << cache_bits if cache_bits else 0
    literal = np.ones(len(v), bool)
    for a, n, _ in copies:
        literal[a : a + n] = False
    green = c[:, 1].astype(np.int64)
    cached = np.zeros(len(v), bool)
    if cache_bits:
        slots, cache = ((v.astype(np.uint64) * 0x1E35A7BD & 0xFFFFFFFF) >> np.uint64(32 - cache_bits)).tolist(), [0] * size
        for i, (k, x) in enumerate(zip(slots, v.tolist(), strict=True)):
            if cache[k] == x and literal[i]:
                cached[i], green[i] = True, 280 + k
            cache[k] = x
    plain = literal & ~cached
    heads = [(a, *prefix_of(n), *prefix_of(d + 120)) for a, n, d in copies]
    counts = np.bincount(green[literal], minlength=280 + size)
    far = np.zeros(40, np.int64)
    for h in heads:
        counts[256 + h[1]] += 1
        far[h[4]] += 1
    lengths = [huffman_lengths(counts, 12)]
    lengths += [huffman_lengths(np.bincount(c[plain, k], minlength=256), 12) for k in (2, 0, 3)]
    lengths.append(huffman_lengths(far, 12))
    for x in lengths:
        write_code(f, x)
    codes = [np.zeros(len(x), np.uint32) if np.count_nonzero(x) < 2 else canonical(x) for x in lengths]
    sizes = [np.zeros(len(x), np.int64) if np.count_nonzero(x) < 2 else x.astype(np.int64) for x in lengths]
    value, bits = codes[0].astype(np.uint64)[green], sizes[0][green]
    for k, ch in ((1, 2), (2, 0), (3, 3)):
        if sizes[k].any():
            s = c[:, ch]
            value = np.where(plain, value | codes[k].astype(np.uint64)[s] << bits.astype(np.uint64), value)
            bits = np.where(plain, bits + sizes[k][s], bits)
    at = 0
    for (a, n, _), (_, lp, lx, ln, dp, dx, dn) in zip(copies, heads, strict=True):
        f.extend(value[at:a], bits[at:a])
        for k, s, x, m in ((0, 256 + lp, lx, ln), (4, dp, dx, dn)):
            f.put(int(codes[k][s]), int(sizes[k][s]))
            f.put(x, m)
        at = a + n
    f.extend(value[at:], bits[at:])


def encode(v: np.ndarray, copies: list[tuple[int, int, int]] = (), transforms: tuple = (), cache_bits: int = 0) -> bytes:
    """A lossless WebP file of ARGB pixels (height, width).

    transforms, in order: ("predictor", bits, modes), ("cross", bits, parts), ("green",), ("palette",)."""
    height, width = v.shape
    alpha = bool((v >> 24 != 255).any())
    f = Fields()
    for x, n in ((width - 1, 14), (height - 1, 14), (alpha, 1), (0, 3)):
        f.put(int(x), n)
    for kind, *rest in transforms:
        f.put(1, 1)
        f.put({"predictor": 0, "cross": 1, "green": 2, "palette": 3}[kind], 2)
        if kind in ("predictor", "cross"):
            f.put(rest[0] - 2, 3)
            write_image(f, rest[1].ravel(), [], False)
            v = (run_predictor if kind == "predictor" else run_cross_colour)(v, rest[1], rest[0], True)
        elif kind == "green":
            v = subtract_green(v, True)
        else:
            table, index = np.unique(v, return_inverse=True)
            index = index.reshape(v.shape)
            f.put(len(table) - 1, 8)
            write_image(f, _numbers(np.diff(_channels(table).astype(np.int16), axis=0, prepend=np.zeros((1, 4), np.int16)).astype(np.uint8)), [], False)
            k = packing_bits(len(table))
            if k:
                each = 8 >> k
                index = np.pad(index, ((0, 0), (0, -v.shape[1] % (1 << k)))).reshape(height, -1, 1 << k)
                index = (index << (each * np.arange(1 << k))).sum(axis=2)
            v = np.uint32(BLACK) | index.astype(np.uint32) << np.uint32(8)
    f.put(0, 1)
    write_image(f, v.ravel(), list(copies), True, cache_bits)
    body = b"\x2f" + f.bytes()
    pad = b"\0" * (len(body) & 1)
    return b"RIFF" + struct.pack("<I", 12 + len(body) + len(pad)) + b"WEBPVP8L" + struct.pack("<I", len(body)) + body + pad
