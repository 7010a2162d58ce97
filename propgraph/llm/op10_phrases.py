"""Removal of repeated 50-byte strings by prefix-free parsing.

Parsing: a rolling hash of 20 bytes triggers a phrase where it becomes, or stops being, the least of the
31 that a 50-byte string holds. So every 50-byte string lies in one phrase, told by its own bytes alone,
and phrases overlap by 49 bytes. The dictionary is the distinct phrases; its occurrences, the parse, follow
in the order of their documents. An occurrence goes whole if a smaller document has the phrase, however
often the corpus repeats it (phrases are told by 128 bits of hash, trigger and whole).

Strings of different phrases can match only if these share a trigger. So of dictionary phrases that share
one, by the least document that has each, the suffixes are put in order, anchored at the trigger: what
follows it is sorted bytewise, and what stands before it, read backwards; both orders come with the lengths
of their neighbours' common prefixes. A 50-byte string is so many bytes before the trigger and the rest
from it on, so equal strings are those whose places fall into the same stretch of both orders: bytes are
compared, not hashes. All suffixes of the dictionary in one order would move fifty times the text; suffixes of
phrases whose trigger no other phrase has can't match and are never ordered.

A trigger that over HOT dictionary phrases share isn't ordered in one task: its phrases' strings are dealt out
one by one, by a hash of the whole string, and compared by 96 bits of two hashes.

Cases: null text is empty; texts under 50 bytes lose nothing; a string repeated only within its own
document stays; rows that share a doc_id, be their texts equal or not, are one document's, none smaller than
the other, and each loses bytes of its own text; a null doc_id takes no part and loses nothing; an empty
table gives no row. Only doc_id and text are read.
"""

from __future__ import annotations

import functools
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import U64, Spans, as_bytes, blocks, release, table, text_of, workers_can_import, written

LENGTH, GRAM, LONGEST = 50, 20, 1000
#: Ids with several texts that are sent to every task; more are joined by shuffle.
MOST_BROADCAST = 100_000
#: Dictionary phrases of one trigger that one task puts in order; rows of phrases that it orders at a time.
HOT, AT_ONCE = 50_000, 16_000
#: A phrase's place: its start times this, plus how many strings it holds.
UNIT = 1024


def phrases(off: np.ndarray, spans: Spans, length: int = LENGTH) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """(document, start, number of strings, trigger) of all phrases of a block of texts."""
    n = np.maximum(np.diff(off) - length + 1, 0)
    doc = np.repeat(np.arange(len(n)), n)
    at = np.repeat(off[:-1] - (np.cumsum(n) - n), n) + np.arange(int(n.sum()))
    low = triggers(spans, int(off[-1]))[at]
    if not len(at):
        return doc, at, at, low
    new = np.flatnonzero(np.append(True, (low[1:] != low[:-1]) | (doc[1:] != doc[:-1])))
    size = np.diff(np.append(new, len(at)))
    # a long run of one trigger, as periodic text has, is cut
    parts = -(-size // LONGEST)
    if (parts > 1).any():
        k = np.repeat(np.arange(len(new)), parts)
        inner = (np.arange(len(k)) - np.repeat(np.cumsum(parts) - parts, parts)) * LONGEST
        new, size = new[k] + inner, np.minimum(LONGEST, size[k] - inner)
    return doc[new], at[new], size, low[new]


def triggers(spans: Spans, total: int, length: int = LENGTH, gram: int = GRAM) -> np.ndarray:
    """The least 20-byte hash of the string at every place; places near a document's end mean nothing."""
    q = np.arange(max(0, total - gram + 1))
    low = spans.of(q, q + gram)
    width, have = length - gram + 1, 1
    while 2 * have <= width:
        low = np.minimum(low[: len(low) - have], low[have:]) if len(low) > have else low[:0]
        have *= 2
    rest = width - have
    return np.minimum(low[: len(low) - rest], low[rest:]) if len(low) > rest else low[:0]


def _rows(names: list[str], *cols: np.ndarray) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array(c) for c in cols], names=names)


def _first(*keys: np.ndarray) -> np.ndarray:
    out = np.ones(len(keys[0]), bool)
    if len(out):
        out[1:] = keys[0][1:] != keys[0][:-1]
        for k in keys[1:]:
            out[1:] |= k[1:] != k[:-1]
    return out


def matched_phrases(texts: DataFrame) -> DataFrame:
    """t, doc_id, ver, place, repeated: phrases that a smaller document has (true), and the least document's
    phrases whose trigger t another phrase has too (false)."""

    def emit(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in blocks(batches, most=1 << 19):
            ids, ver = (np.asarray(batch.column(c), dtype=np.int64) for c in ("doc_id", "ver"))
            buf, off = as_bytes(batch.column("text"))
            spans = Spans(buf)
            doc, at, n, t = phrases(off, spans)
            name = spans.of(at, at + n + LENGTH - 1).view(np.int64)
            t, d, v, place = t.view(np.int64), ids[doc], ver[doc], (at - off[doc]) * UNIT + n
            order = np.lexsort((d, name, t))
            t, name, d, v, place = t[order], name[order], d[order], v[order], place[order]
            head = _first(t, name)
            # a smaller document of this block settles it: such a row needn't look for others
            late = d > d[head][np.cumsum(head) - 1] if len(d) else head
            yield _rows(["t", "name", "doc_id", "ver", "place"], t, name, d, v, np.where(late, -place, place))

    def find(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        # of the open group: its trigger, last name, that name's least document, if shared, and rows that wait to know
        last_t = last_name = least = None
        shared, wait = False, (np.zeros(0, np.int64),) * 4
        for batch in batches:
            t, name, d, v, place = (np.asarray(batch.column(c)) for c in ("t", "name", "doc_id", "ver", "place"))
            late = place < 0
            gone = [(0 * d[late], d[late], v[late], -place[late])]
            open_ = []
            t, name, d, v, place = t[~late], name[~late], d[~late], v[~late], place[~late]
            if len(t):
                ht, hn = _first(t), _first(t, name)
                gt, gn = np.cumsum(ht) - 1, np.cumsum(hn) - 1
                firsts = d[hn].copy()
                names = np.bincount(gt[hn])
                if last_t is not None and t[0] == last_t:
                    if name[0] == last_name:
                        firsts[0] = least
                    else:
                        names[0] += 1
                    if shared:
                        names[0] = 2
                    if names[0] > 1:
                        open_.append(wait)
                    keep = wait if names[0] < 2 and gt[-1] == 0 else None
                else:
                    keep = None
                first = d == firsts[gn]
                gone.append((0 * d[~first], d[~first], v[~first], place[~first]))
                many = names[gt] > 1
                open_.append((t[first & many], d[first & many], v[first & many], place[first & many]))
                last_t, last_name, least, shared = t[-1], name[-1], firsts[-1], bool(names[-1] > 1)
                hold = first & ~many & (gt == gt[-1])
                wait = (t[hold], d[hold], v[hold], place[hold])
                if keep is not None:
                    wait = tuple(np.concatenate(x) for x in zip(keep, wait, strict=True))
            for rows, kind in ((gone, True), (open_, False)):
                for u, x, y, p in rows:
                    if len(x):
                        yield _rows(["t", "doc_id", "ver", "place", "repeated"], u, x, y, p, np.full(len(x), kind))

    rows = texts.mapInArrow(emit, "t long, name long, doc_id long, ver long, place long")
    route = F.when(F.col("place") < 0, F.xxhash64("doc_id", "place")).otherwise(F.col("t"))
    rows = rows.repartition(route).sortWithinPartitions("t", "name", "doc_id")
    return rows.mapInArrow(find, "t long, doc_id long, ver long, place long, repeated boolean")


def asked_texts(texts: DataFrame, asked: DataFrame) -> DataFrame:
    """doc_id, ver, text, places: texts with phrases in question, and these."""
    places = asked.groupBy("doc_id", "ver").agg(F.collect_list("place").alias("places"))
    return texts.join(places, ["doc_id", "ver"]).select("doc_id", "ver", "text", "places")


def anchors(h: np.ndarray, at: np.ndarray, n: np.ndarray, width: int = LENGTH - GRAM + 1) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """(phrase, start, strings, trigger, anchor) of phrases cut so that all strings of one have their first
    least hash at one place, `anchor` bytes after its start. h: the hash at every place."""
    last, wide = len(h) - 1, np.arange(2 * width - 1)
    t = np.empty(len(at), np.uint64)
    out = []
    for a in range(0, len(at), 1 << 12):
        part = slice(a, a + (1 << 12))
        near = h[np.minimum(at[part, None] + wide, last)]
        t[part] = near[:, :width].min(axis=1)
        hit = (near == t[part, None]) & (wide < (n[part] + width - 1)[:, None])
        one = (n[part] <= width) & (hit.sum(axis=1) == 1)
        k = a + np.flatnonzero(one)
        out.append((k, at[k], n[k], hit[one].argmax(axis=1)))
        many = a + np.flatnonzero(~one)
        for b in range(0, len(many), 16):
            k = many[b : b + 16]
            k = np.repeat(k, n[k])
            inner = np.arange(len(k)) - np.searchsorted(k, k)
            start = at[k] + inner
            place = start + (h[start[:, None] + np.arange(width)] == t[k, None]).argmax(axis=1)
            new = np.flatnonzero(_first(k, place))
            out.append((k[new], start[new], np.diff(np.append(new, len(k))), (place - start)[new]))
    k, start, size, anchor = (np.concatenate(x) for x in zip(*out, strict=True)) if out else (np.zeros(0, np.int64),) * 4
    return k, start, size, t[k], anchor


def common_prefixes(rows: np.ndarray, order: np.ndarray, group: np.ndarray) -> np.ndarray:
    """Of rows of bytes in order: how many first bytes each shares with the one before; -1 at a group's first."""
    out = np.full(len(order), -1, np.int64)
    if len(order) > 1:
        unlike = rows[order[1:]] != rows[order[:-1]]
        long = np.where(unlike.any(axis=1), unlike.argmax(axis=1), rows.shape[1])
        out[1:] = np.where(group[order[1:]] == group[order[:-1]], long, -1)
    return out


def in_order(rows: np.ndarray, group: np.ndarray) -> np.ndarray:
    """The rows' bytewise order within their groups."""
    words = np.pad(rows, ((0, 0), (0, -rows.shape[1] % 8))).view(">u8")
    return np.lexsort([*(words[:, i] for i in range(words.shape[1] - 1, -1, -1)), group])


def ordered_matches(t: np.ndarray, doc: np.ndarray, n: np.ndarray, anchor: np.ndarray, data: np.ndarray, off: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(phrase, first string, strings): runs of strings that a phrase of a smaller document has, of whole trigger groups."""
    r = len(t)
    before, after = LENGTH - GRAM, LENGTH
    off = off.astype(np.int32)
    at = (off[:-1] + anchor.astype(np.int32))[:, None] + np.arange(after, dtype=np.int32)
    ahead = np.where(at < off[1:, None], data[np.minimum(at, len(data) - 1)], 0).astype(np.uint8)
    at = (off[:-1] + anchor.astype(np.int32))[:, None] - 1 - np.arange(before, dtype=np.int32)
    back = np.where(at >= off[:-1, None], data[np.maximum(at, 0)], 0).astype(np.uint8)
    orders = [in_order(x, t) for x in (ahead, back)]
    common = [common_prefixes(x, o, t) for x, o in zip((ahead, back), orders, strict=True)]
    rank = [np.empty(r, np.int64) for _ in orders]
    for o, k in zip(orders, rank, strict=True):
        k[o] = np.arange(r)
    gone = np.zeros((r, before + 2), bool)
    for k in range(before + 1):
        # strings with k bytes before the trigger: equal where both parts lie in one stretch of their order
        some = np.flatnonzero((anchor >= k) & (anchor - n < k))
        if not len(some):
            continue
        right, left = (np.cumsum(c < m)[q[some]] for c, m, q in ((common[0], LENGTH - k, rank[0]), (common[1], k, rank[1])))
        order = np.lexsort((doc[some], left, right))
        d, right, left = doc[some][order], right[order], left[order]
        head = _first(right, left)
        late = d > d[head][np.cumsum(head) - 1]
        hit = some[order[late]]
        gone[hit, anchor[hit] - k] = True
    edge = np.diff(gone.astype(np.int8), axis=1, prepend=0)
    row, first = np.nonzero(edge == 1)
    _, end = np.nonzero(edge == -1)
    return row, first, end - first


def matched_suffixes(asked: DataFrame) -> DataFrame:
    """doc_id, ver, place: runs of strings, of the phrases in question, that a smaller document has, found in suffix order."""

    def emit(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in blocks(batches, most=1 << 19):
            ids, ver = (np.asarray(batch.column(c), dtype=np.int64) for c in ("doc_id", "ver"))
            buf, off = as_bytes(batch.column("text"))
            lists = batch.column("places")
            place = np.asarray(lists.flatten())
            doc = np.repeat(np.arange(batch.num_rows), np.diff(np.asarray(lists.offsets)))
            q = np.arange(max(0, len(buf) - GRAM + 1))
            k, at, n, t, anchor = anchors(Spans(buf).of(q, q + GRAM), off[doc] + place // UNIT, place % UNIT)
            size = n + LENGTH - 1
            end = np.cumsum(size)
            data = buf[np.repeat(at - (end - size), size) + np.arange(int(size.sum()))]
            rows = pa.BinaryArray.from_buffers(pa.binary(), len(size), [None, pa.py_buffer(np.concatenate([[0], end]).astype(np.int32)), pa.py_buffer(data)])
            own = doc[k]
            cols = [pa.array(x) for x in (t.view(np.int64), ids[own], ver[own], ((at - off[own]) << 12) | (n << 6) | anchor)]
            yield pa.RecordBatch.from_arrays([*cols, rows], names=["t", "doc_id", "ver", "place", "phrase"])

    def find(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        def done(table: pa.Table) -> pa.RecordBatch:
            t, d, v, p = (np.asarray(table.column(c), dtype=np.int64) for c in ("t", "doc_id", "ver", "place"))
            data, off = as_bytes(table.column("phrase"))
            row, first, n = ordered_matches(t, d, (p >> 6) & 63, p & 63, data, off)
            return _rows(["doc_id", "ver", "place"], d[row], v[row], ((p >> 12)[row] + first) * UNIT + n)

        held, count = [], 0
        for batch in batches:
            held.append(batch)
            count += batch.num_rows
            if count < AT_ONCE:
                continue
            table = pa.Table.from_batches(held)
            t = np.asarray(table.column("t"))
            cut = int(np.searchsorted(t, t[-1]))  # the last group may go on
            if cut:
                yield done(table.slice(0, cut))
            held, count = table.slice(cut).to_batches(), len(t) - cut
        if count:
            yield done(pa.Table.from_batches(held))

    rows = asked.mapInArrow(emit, "t long, doc_id long, ver long, place long, phrase binary")
    return rows.repartition("t").sortWithinPartitions("t").mapInArrow(find, "doc_id long, ver long, place long")


def repeated_strings(asked: DataFrame) -> DataFrame:
    """doc_id, ver, place: starts of strings, of the phrases in question, that a smaller document has, by hashes of the strings."""

    def emit(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in blocks(batches, most=1 << 19):
            ids, ver = (np.asarray(batch.column(c), dtype=np.int64) for c in ("doc_id", "ver"))
            buf, off = as_bytes(batch.column("text"))
            lists = batch.column("places")
            size = np.diff(np.asarray(lists.offsets))
            place = np.asarray(lists.flatten())
            doc = np.repeat(np.arange(batch.num_rows), size)
            n = place % UNIT
            k = np.repeat(np.arange(len(place)), n)
            at = (off[doc] + place // UNIT)[k] + np.arange(len(k)) - np.repeat(np.cumsum(n) - n, n)
            w = Spans(buf).of(at, at + LENGTH).view(np.int64)
            check = (Spans(buf, seed=2).of(at, at + LENGTH) >> U64(32)).view(np.int64)
            d, v, at = ids[doc[k]], ver[doc[k]], at - off[doc[k]]
            order = np.lexsort((d, check, w))
            w, check, d, v, at = w[order], check[order], d[order], v[order], at[order]
            head = _first(w, check)
            late = d > d[head][np.cumsum(head) - 1] if len(d) else head
            # the start takes 31 bits, the check the 32 above them
            yield _rows(["w", "doc_id", "ver", "place"], w, d, v, np.where(late, -1 - at, (check << 31) | at))

    def find(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        last = least = None
        for batch in batches:
            w, d, v, p = (np.asarray(batch.column(c)) for c in ("w", "doc_id", "ver", "place"))
            late = p < 0
            out = [(d[late], v[late], -1 - p[late])]
            w, d, v, p = w[~late], d[~late], v[~late], p[~late]
            if len(w):
                check = p >> 31
                head = _first(w, check)
                first = d[head].copy()
                if last == (w[0], check[0]):
                    first[0] = least
                last, least = (w[-1], check[-1]), first[-1]
                gone = d > first[np.cumsum(head) - 1]
                out.append((d[gone], v[gone], p[gone] & ((1 << 31) - 1)))
            for x, y, q in out:
                if len(x):
                    yield _rows(["doc_id", "ver", "place"], x, y, q)

    rows = asked.mapInArrow(emit, "w long, doc_id long, ver long, place long")
    route = F.when(F.col("place") < 0, F.xxhash64("doc_id", "place")).otherwise(F.col("w"))
    rows = rows.repartition(route).sortWithinPartitions("w", F.shiftright("place", 31), "doc_id")
    return rows.mapInArrow(find, "doc_id long, ver long, place long")


def versions(docs: DataFrame) -> DataFrame:
    """doc_id, text, ver: 0, or a hash of the text where an id has rows of different texts."""
    tag: Column = F.xxhash64(F.coalesce("text", F.lit("")))
    texts = text_of(docs, tag.alias("tag"))
    several = texts.where("doc_id IS NOT NULL").groupBy("doc_id").agg(F.min("tag").alias("a"), F.max("tag").alias("b")).where("a != b")
    several = written(several.select("doc_id", F.lit(True).alias("several")), "several-texts")
    n = several.count()
    if not n:
        return texts.select("doc_id", "text", F.lit(0).cast("long").alias("ver"))
    rows = texts.join(F.broadcast(several) if n <= MOST_BROADCAST else several, "doc_id", "left")
    return rows.select("doc_id", "text", F.when(F.col("several"), F.col("tag")).otherwise(F.lit(0)).cast("long").alias("ver"))


def remove_repeats(docs: DataFrame) -> DataFrame:
    """doc_id, kept (bytes), n_bytes, n_removed, spans (starts and ends of removed runs)."""
    spark = docs.sparkSession
    workers_can_import(spark)
    texts = versions(docs)
    known = texts.where("doc_id IS NOT NULL")
    matched = written(matched_phrases(known), "phrases")
    found = [matched.where("repeated").select("doc_id", "ver", "place")]
    phrases_ = matched.where("NOT repeated")
    hot = written(phrases_.groupBy("t").agg(F.count("*").alias("n")).where(F.col("n") > HOT).select("t"), "hot-triggers")
    n = hot.count()
    if n:
        many = F.broadcast(hot) if n <= MOST_BROADCAST else hot
        # tables, so that the shuffled texts are gone before what is made of them is shuffled
        asked = written(asked_texts(known, phrases_.join(many, "t", "left_semi")), "asked-texts")
        strings = written(repeated_strings(asked), "strings")
        release(asked)
        found.append(strings.select("doc_id", "ver", (F.col("place") * UNIT + 1).alias("place")))
        phrases_ = phrases_.join(many, "t", "left_anti")
    asked = written(asked_texts(known, phrases_), "asked-texts")
    found.append(written(matched_suffixes(asked), "suffixes"))
    release(asked)
    gone = functools.reduce(DataFrame.unionByName, found)
    marks = gone.groupBy("doc_id", "ver").agg(F.collect_list("place").alias("places"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in blocks(batches, most=1 << 19):
            raw, off = as_bytes(batch.column("text"))
            lists = batch.column("places")
            flat, ends = np.asarray(lists.flatten()), np.asarray(lists.offsets)
            valid = np.asarray(lists.is_valid())
            kept, removed, runs = [], [], []
            for i in range(batch.num_rows):
                text = raw[off[i] : off[i + 1]]
                place = flat[ends[i] - ends[0] : ends[i + 1] - ends[0]]
                if not valid[i] or not len(place):
                    kept.append(text.tobytes())
                    removed.append(0)
                    runs.append([])
                    continue
                change = np.zeros(len(text) + 1, np.int64)
                np.add.at(change, place // UNIT, 1)
                np.add.at(change, place // UNIT + place % UNIT + LENGTH - 1, -1)
                covered = np.cumsum(change)[:-1] > 0
                edge = np.flatnonzero(np.diff(np.concatenate([[0], covered.astype(np.int8), [0]])))
                kept.append(text[~covered].tobytes())
                removed.append(int(covered.sum()))
                runs.append(edge.tolist())
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), pa.array(kept, pa.binary()), pa.array(np.diff(off)), pa.array(removed, pa.int64()), pa.array(runs, pa.list_(pa.int64()))], names=["doc_id", "kept", "n_bytes", "n_removed", "spans"])

    return texts.join(marks, ["doc_id", "ver"], "left").select("doc_id", "text", "places").mapInArrow(run, "doc_id long, kept binary, n_bytes long, n_removed long, spans array<long>")


def op10_phrase_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = remove_repeats(table(spark, sf_dir, "documents"))
    return rows.select("doc_id", "n_bytes", "n_removed", (F.size("spans") / 2).cast("long").alias("n_spans"), F.sha2("kept", 256).alias("kept_sha256"))


ORACLE = f"""
WITH d AS MATERIALIZED (SELECT doc_id, hex(encode(coalesce(text, ''))) AS x, octet_length(encode(coalesce(text, '')))::BIGINT AS n FROM documents),
q AS (SELECT doc_id, n, i, substr(x, 2 * i + 1, {2 * LENGTH}) AS s FROM d, LATERAL (SELECT unnest(range(0, n - {LENGTH - 1})) AS i) r),
m AS MATERIALIZED (SELECT doc_id, i FROM (SELECT doc_id, i, min(doc_id) OVER (PARTITION BY s) AS first FROM q) t WHERE first < doc_id),
b AS (SELECT doc_id, i, coalesce(i > lag(i) OVER w + {LENGTH}, true) AS new FROM m WINDOW w AS (PARTITION BY doc_id ORDER BY i)),
r AS (SELECT doc_id, i, sum(new::INT) OVER (PARTITION BY doc_id ORDER BY i) AS run FROM b),
g AS MATERIALIZED (SELECT doc_id, run, min(i) AS a, max(i) + {LENGTH} AS e FROM r GROUP BY doc_id, run),
c AS (SELECT doc_id, a AS e, coalesce(lag(e) OVER (PARTITION BY doc_id ORDER BY a), 0) AS a FROM g UNION ALL SELECT doc_id, n, coalesce((SELECT max(e) FROM g WHERE g.doc_id = d.doc_id), 0) FROM d),
k AS (SELECT c.doc_id, string_agg(substr(x, 2 * a + 1, 2 * (c.e - a)), '' ORDER BY a) AS x FROM c JOIN d ON d.doc_id = c.doc_id GROUP BY c.doc_id)
SELECT d.doc_id, n AS n_bytes, coalesce(t.removed, 0)::BIGINT AS n_removed, coalesce(t.runs, 0)::BIGINT AS n_spans, sha256(unhex(k.x)) AS kept_sha256
FROM d JOIN k ON k.doc_id = d.doc_id LEFT JOIN (SELECT doc_id, sum(e - a) AS removed, count(*) AS runs FROM g GROUP BY doc_id) t ON t.doc_id = d.doc_id
"""
