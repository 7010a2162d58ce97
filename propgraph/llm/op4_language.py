"""Language identification by a bidirectional gated recurrent network over bytes, in numpy.

One layer reads a text's bytes forwards, one backwards; at every position the two states give
log-probabilities of the languages, so every byte of a text is labelled. A document's log-probabilities
are the sums over all its positions; the score is the softmax of their mean, sharpened by SHARP.

Whole texts are read in windows of at most SPAN labelled bytes. A window's forward state starts REACH
bytes before its first labelled byte, its backward state REACH bytes after the last (or at the text's
ends), so that memory stays bounded for texts of any length while every label has seen at least that
much running text on either side. Windows of all texts of a block are stepped through together, longest first.

Training: backpropagation through time with Adam on a bounded sample: TRAIN_WINDOWS stretches of
TRAIN_BYTES code points, evenly spread, of each of the TRAIN_DOCS documents of each language with the
least hash of doc_id; only rows with a known language and crc32(doc_id) mod 4 other than 2.
All else, i.e. every prediction, covers all rows and whole texts.

Cases: a null text or one without any letter (Unicode category L) is `und` with score 0; so is every text
if nothing could be learned (no labelled row). Null doc_ids are held in (their crc32 is null) but never
trained on. Repeated rows are predicted alike; only doc_id, text and, for training, lang are read.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import as_bytes, blocks, table, workers_can_import

HIDDEN, EMBED, SPAN, REACH = 12, 8, 512, 32
TRAIN_DOCS, TRAIN_WINDOWS, TRAIN_BYTES, EPOCHS, BATCH, RATE, SHARP = 200, 6, 64, 5, 128, 0.012, 8.0
UND = "und"


def sigmoid(x: np.ndarray) -> np.ndarray:
    return np.float32(0.5) * (np.tanh(np.float32(0.5) * x) + np.float32(1))


class ByteGru:
    """Two gated recurrent layers, one a direction, and a linear layer on both states.

    The reset gate acts on the former state's product with its weights, so that a step has one product."""

    def __init__(self, labels: list[str], hidden: int = HIDDEN, embed: int = EMBED, seed: int = 7) -> None:
        r = np.random.default_rng(seed)
        self.labels, self.h = labels, hidden
        w = lambda a, b: (r.standard_normal((a, b)) / np.sqrt(a)).astype(np.float32)
        self.p = {"emb": w(256, embed) * np.float32(np.sqrt(256)) * np.float32(0.3)}
        for d in "fb":
            self.p |= {f"w{d}": w(embed, 3 * hidden), f"u{d}": w(hidden, 3 * hidden), f"c{d}": np.zeros(3 * hidden, np.float32)}
        self.p |= {"out": w(2 * hidden, len(labels)), "bias": np.zeros(len(labels), np.float32)}

    def states(self, ids: np.ndarray, mask: np.ndarray, d: str, keep: list) -> np.ndarray:
        """For training: states (t, n, h) over bytes (n, t), right-padded; direction b starts at each row's end."""
        n, t = ids.shape
        h, u = self.h, self.p[f"u{d}"]
        tab = self.p["emb"] @ self.p[f"w{d}"] + self.p[f"c{d}"]
        s = np.zeros((n, h), u.dtype)
        out = np.empty((t, n, h), u.dtype)
        for i in range(t) if d == "f" else range(t - 1, -1, -1):
            x, y = tab[ids[:, i]], s @ u
            g = sigmoid(x[:, : 2 * h] + y[:, : 2 * h])
            z, r = g[:, :h], g[:, h:]
            c = np.tanh(x[:, 2 * h :] + r * y[:, 2 * h :])
            m = mask[:, i : i + 1]
            keep.append((i, s, z, r, c, y[:, 2 * h :], m))
            s = s + m * z * (c - s)
            out[i] = s
        return out

    def gradients(self, ids: np.ndarray, mask: np.ndarray, want: np.ndarray) -> tuple[float, dict[str, np.ndarray]]:
        p, h = self.p, self.h
        kept: dict[str, list] = {"f": [], "b": []}
        s = {d: self.states(ids, mask, d, kept[d]) for d in "fb"}
        both = np.concatenate([s["f"], s["b"]], axis=2)
        y = both @ p["out"] + p["bias"]
        y -= y.max(axis=2, keepdims=True)
        prob = np.exp(y)
        prob /= prob.sum(axis=2, keepdims=True)
        m = mask.T[:, :, None]
        total = m.sum()
        loss = -float((np.log(np.take_along_axis(prob, want[None, :, None].repeat(len(y), 0), 2) + 1e-9) * m).sum() / total)
        dy = prob
        dy[:, np.arange(len(want)), want] -= 1
        dy *= m / total
        g = {k: np.zeros_like(v) for k, v in p.items()}
        g["out"] = np.tensordot(both, dy, axes=([0, 1], [0, 1]))
        g["bias"] = dy.sum(axis=(0, 1))
        dboth = dy @ p["out"].T
        for d, ds_all in (("f", dboth[:, :, :h]), ("b", dboth[:, :, h:])):
            u, carry = p[f"u{d}"], np.zeros((len(ids), h), p["out"].dtype)
            seen = np.zeros((256, 3 * h), p["out"].dtype)
            for i, prev, z, r, c, y_c, mk in reversed(kept[d]):
                ds = carry + ds_all[i]
                dz = ds * mk * (c - prev) * z * (1 - z)
                dc = ds * mk * z * (1 - c * c)
                dr = dc * y_c * r * (1 - r)
                into = np.concatenate([dz, dr, dc * r], axis=1)
                g[f"u{d}"] += prev.T @ into
                into[:, 2 * h :] = dc
                np.add.at(seen, ids[:, i], into)
                into[:, 2 * h :] *= r
                carry = ds * (1 - mk * z) + into @ u.T
            g[f"c{d}"] += seen.sum(axis=0)
            g[f"w{d}"] += p["emb"].T @ seen
            g["emb"] += seen @ p[f"w{d}"].T
        return loss, g

    def fit(self, segments: list[bytes], want: np.ndarray, epochs: int = EPOCHS, rate: float = RATE, seed: int = 11) -> list[float]:
        r = np.random.default_rng(seed)
        m1 = {k: np.zeros_like(v) for k, v in self.p.items()}
        m2 = {k: np.zeros_like(v) for k, v in self.p.items()}
        step, losses = 0, []
        for epoch in range(epochs):
            order = r.permutation(len(segments))
            total = []
            for a in range(0, len(order), BATCH):
                at = order[a : a + BATCH]
                ids, mask = padded([segments[i] for i in at])
                loss, g = self.gradients(ids, mask, want[at])
                total.append(loss)
                step += 1
                lr = rate * (1 - epoch / epochs)
                for k, v in g.items():
                    m1[k] = 0.9 * m1[k] + 0.1 * v
                    m2[k] = 0.99 * m2[k] + 0.01 * v * v
                    self.p[k] -= (lr * (m1[k] / (1 - 0.9**step)) / (np.sqrt(m2[k] / (1 - 0.99**step)) + 1e-7)).astype(np.float32)
            losses.append(float(np.mean(total)))
        return losses

    def positions(self, raw: np.ndarray, off: np.ndarray, span: int = SPAN, reach: int = REACH) -> np.ndarray:
        """Log-probabilities (bytes, labels) of every byte of the texts raw[off[i]:off[i + 1]]."""
        h, n_labels = self.h, len(self.labels)
        size = np.diff(off)
        parts = -(-size // span)
        text = np.repeat(np.arange(len(size)), parts)
        k = np.arange(len(text)) - np.repeat(np.cumsum(parts) - parts, parts)
        # a text's windows are of nearly the same length
        begin, end = off[text] + size[text] * k // parts[text], off[text] + size[text] * (k + 1) // parts[text]
        y = np.tile(self.p["bias"], (len(raw), 1))
        half = np.ones(3 * h, np.float32)
        half[: 2 * h] = 0.5  # the gates' sigmoid is half a tanh of half its argument, plus a half
        for d, out in (("f", self.p["out"][:h]), ("b", self.p["out"][h:])):
            # features by windows, so that every operation runs along the windows
            tab = np.ascontiguousarray(((self.p["emb"] @ self.p[f"w{d}"] + self.p[f"c{d}"]) * half).T)
            u, out = np.ascontiguousarray((self.p[f"u{d}"] * half).T), np.ascontiguousarray(out.T)
            if d == "f":
                first, step = np.maximum(off[text], begin - reach), 1
                long, late = end - first, begin - first
            else:
                first, step = np.minimum(off[text + 1], end + reach) - 1, -1
                long, late = first - begin + 1, first - end + 1
            order = np.argsort(-long, kind="stable")
            first, late, long = first[order], late[order], long[order]
            steps = np.arange(int(long.max(initial=0)))
            still = np.searchsorted(-long, -steps, side="left").tolist()
            at = first + step * steps[:, None]
            ids = raw[np.clip(at, 0, len(raw) - 1)]
            got = np.empty((len(steps), n_labels, len(order)), np.float32)
            s = np.zeros((h, len(order)), np.float32)
            room_x, room_p = (np.empty(3 * h * len(order), np.float32) for _ in range(2))
            for i, m in enumerate(still):
                if m < s.shape[1]:
                    s = np.ascontiguousarray(s[:, :m])
                x, p = room_x[: 3 * h * m].reshape(3 * h, m), room_p[: 3 * h * m].reshape(3 * h, m)
                np.take(tab, ids[i, :m], axis=1, out=x, mode="clip")
                np.matmul(u, s, out=p)
                g, c = x[: 2 * h], x[2 * h :]
                g += p[: 2 * h]
                np.tanh(g, out=g)
                g *= np.float32(0.5)
                g += np.float32(0.5)
                p[2 * h :] *= g[h:]
                c += p[2 * h :]
                np.tanh(c, out=c)
                c -= s
                c *= g[:h]
                s += c
                got[i, :, :m] = out @ s
            # what lies before a window's first labelled byte has only warmed its state
            read = (steps[:, None] >= late) & (steps[:, None] < long)
            where = at[read]
            for k in range(n_labels):
                y[where, k] += got[:, k][read]
        y -= y.max(axis=1, keepdims=True)
        return y - np.log(np.exp(y).sum(axis=1, keepdims=True))

    def sums(self, raw: np.ndarray, off: np.ndarray) -> np.ndarray:
        """Summed log-probabilities (texts, labels) over each text's positions."""
        out = np.zeros((len(off) - 1, len(self.labels)))
        some = np.flatnonzero(np.diff(off))
        if len(some):
            out[some] = np.add.reduceat(self.positions(raw, off), off[some], axis=0, dtype=np.float64)
        return out


def padded(segments: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
    size = np.fromiter(map(len, segments), np.int64, len(segments))
    t = int(size.max(initial=1))
    ids = np.frombuffer(b"".join(s.ljust(t, b"\0") for s in segments), np.uint8).reshape(len(segments), t)
    return ids, (np.arange(t) < size[:, None]).astype(np.float32)


def training_rows(docs: DataFrame, per_label: int = TRAIN_DOCS, per_doc: int = TRAIN_WINDOWS) -> tuple[list[bytes], list[str]]:
    """At most per_label * per_doc stretches of each language; only these reach the driver."""
    from pyspark.sql import Window

    crc = F.crc32(F.col("doc_id").cast("string"))
    rows = docs.where(F.col("lang").isNotNull() & F.col("text").isNotNull() & (crc % 4 != 2)).select("lang", F.xxhash64("doc_id").alias("h"), "doc_id")
    # a slice of the hash range first, so that the ranking sorts few rows; widened when it holds too few
    chosen = rows.groupBy("lang").agg(F.count("*").alias("n"))
    rows = rows.join(F.broadcast(chosen), "lang").where(F.pmod("h", F.lit(1 << 20)) < F.greatest(F.lit(1), F.ceil(F.lit(4.0 * per_label * (1 << 20)) / F.col("n"))))
    rows = rows.withColumn("k", F.row_number().over(Window.partitionBy("lang").orderBy("h", "doc_id"))).where(F.col("k") <= per_label)
    ids = rows.select("doc_id", "lang").distinct()
    texts = docs.where(F.col("lang").isNotNull() & F.col("text").isNotNull()).select("doc_id", "lang", "text").join(F.broadcast(ids), ["doc_id", "lang"], "left_semi")
    some = F.array_distinct(F.transform(F.sequence(F.lit(0), F.lit(per_doc - 1)), lambda i: F.substring(F.col("text"), (i * F.length("text") / per_doc).cast("int") + 1, F.lit(TRAIN_BYTES))))
    got = texts.select("lang", F.explode(some).alias("s")).where("length(s) > 0").orderBy("lang", F.xxhash64("s"), "s").collect()
    return [r["s"].encode() for r in got], [r["lang"] for r in got]


def train(docs: DataFrame) -> ByteGru | None:
    segments, langs = training_rows(docs)
    labels = sorted(set(langs))
    if not labels:
        return None
    net = ByteGru(labels)
    # every language is learned from as many stretches
    r = np.random.default_rng(5)
    y = np.array([labels.index(x) for x in langs])
    n = min(TRAIN_DOCS * TRAIN_WINDOWS, max(np.bincount(y)))
    at = np.concatenate([r.permutation(np.resize(r.permutation(np.flatnonzero(y == k)), n)) for k in range(len(labels))])
    net.fit([segments[i] for i in at], y[at])
    return net


def label_languages(docs: DataFrame, net: ByteGru | None, carry: bool = False) -> DataFrame:
    """doc_id, lang_pred, score; with carry, instead all of docs' columns in a struct `row` and those two."""
    spark = docs.sparkSession
    workers_can_import(spark)
    head = F.struct(*docs.columns).alias("row") if carry else F.col("doc_id").cast("long").alias("doc_id")
    name = "row" if carry else "doc_id"
    rows = docs.select(head) if carry else docs.select(head, F.col("text").alias("text"))
    kind = rows.schema[name].dataType.simpleString()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        def split(batch: pa.RecordBatch) -> pa.RecordBatch:
            # the carried rows hold the text; it isn't sent twice
            row = batch.column("row")
            return pa.RecordBatch.from_arrays([row, row.field("text")], names=["row", "text"])

        for batch in blocks(map(split, batches) if carry else batches, most=1 << 19):
            texts = batch.column("text").to_pylist()
            known = np.array([t is not None and net is not None and any(map(str.isalpha, t)) for t in texts], bool)
            raw, off = as_bytes(batch.column("text"))
            pred, score = [UND] * len(texts), [0.0] * len(texts)
            if known.any():
                size = np.where(known, np.diff(off), 0)
                raw = raw[np.repeat(known, np.diff(off))]
                total = net.sums(raw, np.concatenate([[0], np.cumsum(size)]))
                y = total / np.maximum(size, 1)[:, None] * SHARP
                y = np.exp(y - y.max(axis=1, keepdims=True))
                y /= y.sum(axis=1, keepdims=True)
                best = total.argmax(axis=1)
                for i in np.flatnonzero(known).tolist():
                    pred[i], score[i] = net.labels[best[i]], float(y[i, best[i]])
            yield pa.RecordBatch.from_arrays([batch.column(name), pa.array(pred, pa.string()), pa.array(score, pa.float64())], names=[name, "lang_pred", "score"])

    return rows.mapInArrow(run, f"{name} {kind}, lang_pred string, score double")


def op4_language(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    got = label_languages(docs, train(docs))
    held = F.coalesce(F.crc32(F.col("doc_id").cast("string")) % 4 == 2, F.lit(False))
    return got.select("doc_id", held.alias("held_out"), "lang_pred", "score")
