"""Quality classifier: logistic regression over hashed word n-grams, trained by follow-the-regularised-leader."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import DoubleType, StructField, StructType

from .common import mix, pieces, text_bytes, word_hashes, word_spans

#: Hashed dimensions: 2**18 weights of 4 bytes are what is sent to the executors, whatever the input.
BITS = 18
#: Labelled rows that training may collect (about 6 kB each): the bound on what comes to the driver.
MOST_TRAIN = 4000
EPOCHS, ALPHA, BETA, L1, L2, SCALE = 4, 0.5, 1.0, 0.02, 1.0, 8.0
THRESHOLD = 0.3

#: Kinds of bytes: capital, small, digit, other sign, beyond ASCII.
_KIND = np.full(256, 8, np.uint8)
_KIND[65:91], _KIND[97:123], _KIND[48:58], _KIND[128:] = 1, 2, 4, 16


def features(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """Index of every n-gram of every text, and where each text's begin.

    A word has two spellings: its lower-cased letters and its shape (kinds of its letters, first and last byte if signs).  N-grams are one or
    two words, one to three shapes, and pairs of a word with itself.
    """
    data, offsets = text_bytes(column)
    starts, ends, first = word_spans(data, offsets)
    n = len(starts)
    if not n:
        return np.zeros(0, np.int64), np.zeros(len(first), np.int64)
    words = word_hashes(data, starts, ends)
    cuts = np.ravel(np.column_stack([starts, ends]))
    # The last cut may be the end of the data, where reduceat has nothing to read.
    kinds = np.bitwise_or.reduceat(np.append(_KIND[data], 0), cuts)[::2].astype(np.uint64)
    head, tail = data[starts], data[ends - 1]
    sign = lambda b: np.where(_KIND[b] == 8, b, _KIND[b] & 3).astype(np.uint64)
    longer = np.minimum(ends - starts, 3).astype(np.uint64)
    shape = kinds | (sign(head) << np.uint64(8)) | (sign(tail) << np.uint64(16)) | (longer << np.uint64(24))
    begins = np.zeros(n, bool)
    begins[first[:-1][first[:-1] < n]] = True
    one, two = np.flatnonzero(~begins), np.flatnonzero(~(begins | np.append(False, begins[:-1])))
    two = two[two >= 2]
    G = np.uint64
    grams = [
        (np.arange(n), mix(words ^ G(0x11))), (one, mix(words[one] * G(3) + words[one - 1] * G(5) + G(0x22))),
        (np.arange(n), mix(shape + G(0x33))), (one, mix(shape[one] * G(0x10001) + mix(shape[one - 1]) + G(0x44))),
        (two, mix(shape[two] + mix(shape[two - 1] + mix(shape[two - 2])) + G(0x55))), (one, np.where(words[one] == words[one - 1], G(0x66), G(0x77))),
    ]
    at = np.concatenate([a for a, _ in grams])
    index = (np.concatenate([g for _, g in grams]) & G((1 << BITS) - 1)).astype(np.int64)
    order = np.argsort(at, kind="stable")
    return index[order], np.searchsorted(at[order], first)


def train(docs: DataFrame, labels: DataFrame, label_col: str = "quality", text_col: str = "text", id_col: str = "doc_id") -> dict:
    """Weights and bias from the texts of at most MOST_TRAIN labelled ids, those first in the order of the md5 of their ids.

    The sample is drawn from the labels alone, so no text is moved but its own.  Null labels are left out; of rows with one id the largest label
    and text count; ids without a document bring nothing.  Without labelled rows, or with one label only, every
    text gets the share of label 1 (0.5 without rows).
    """
    marks = labels.filter(F.col(label_col).isNotNull() & F.col(id_col).isNotNull()).groupBy(id_col).agg(F.max(F.col(label_col).cast("int")).alias("y"))
    sample = marks.select(F.col(id_col).alias("_id"), "y", F.md5(F.col(id_col).cast("string")).alias("h")).orderBy("h").limit(MOST_TRAIN)
    own = docs.select(F.col(id_col).alias("_id"), F.col(text_col).cast("string").alias("text"))
    joined = own.join(F.broadcast(sample), "_id")  # MOST_TRAIN rows
    chosen = joined.groupBy("h", "y").agg(F.max("text").alias("text"))

    def run(batches):
        for whole in batches:
            for batch in pieces(whole, "text"):
                index, first = features(batch.column("text"))
                out = [np.unique(index[a:b], return_counts=True) for a, b in zip(first[:-1], first[1:], strict=True)]
                yield pa.RecordBatch.from_arrays([batch.column("h"), batch.column("y"), pa.array([i.astype("<i4").tobytes() for i, _ in out], pa.binary()), pa.array([c.astype("<u4").tobytes() for _, c in out], pa.binary())], ["h", "y", "i", "c"])

    rows = chosen.mapInArrow(run, "h string, y int, i binary, c binary").collect()
    rows.sort(key=lambda r: (r.h, r.y))
    return fit([(np.frombuffer(r.i, "<i4"), np.frombuffer(r.c, "<u4").astype(np.float64), r.y) for r in rows])


def fit(rows: list[tuple[np.ndarray, np.ndarray, int]]) -> dict:
    """Follow-the-regularised-leader, one row at a time, EPOCHS times over; the bias is its own coordinate, not regularised."""
    z, n = np.zeros(1 << BITS), np.zeros(1 << BITS)
    share = float(np.mean([y for *_, y in rows])) if rows else 0.5
    share = min(max(share, 1e-3), 1 - 1e-3)
    bias, bias_n = float(np.log(share / (1 - share))), 1.0
    if len({y for *_, y in rows}) > 1:
        for _ in range(EPOCHS):
            for index, count, y in rows:
                x = SCALE * count / max(count.sum(), 1)
                zi, ni = z[index], n[index]
                w = np.where(np.abs(zi) <= L1, 0.0, -(zi - np.sign(zi) * L1) / ((BETA + np.sqrt(ni)) / ALPHA + L2))
                p = 1 / (1 + np.exp(-np.clip(bias + w @ x, -35, 35)))
                g = (p - y) * x
                new = ni + g * g
                z[index] = zi + g - (np.sqrt(new) - np.sqrt(ni)) / ALPHA * w
                n[index] = new
                bias_n += (p - y) ** 2
                bias -= 0.1 * (p - y) / np.sqrt(bias_n)
    w = np.where(np.abs(z) <= L1, 0.0, -(z - np.sign(z) * L1) / ((BETA + np.sqrt(n)) / ALPHA + L2))
    return {"w": w.astype(np.float32), "bias": bias}


def scores(column: pa.Array, w: np.ndarray, bias: float) -> np.ndarray:
    index, first = features(column)
    sizes = np.diff(first)
    total = np.zeros(len(sizes))
    if len(index):
        full = sizes > 0
        total[full] = np.add.reduceat(w[index].astype(np.float64), first[:-1][full])
    return 1 / (1 + np.exp(-np.clip(bias + SCALE * total / np.maximum(sizes, 1), -35, 35)))


def score(docs: DataFrame, model: dict, text_col: str = "text") -> DataFrame:
    """docs with a further column quality_score (0 to 1), from the text alone; null and empty texts score by the bias.

    All columns pass through unchanged, clashing names apart: a column quality_score of docs is replaced.  Equal texts score the same."""
    docs = docs.drop("quality_score")
    sent = docs.sparkSession.sparkContext.broadcast((model["w"], model["bias"]))

    def run(batches):
        w, bias = sent.value
        for whole in batches:
            for batch in pieces(whole, text_col):
                s = scores(batch.column(text_col), w, bias)
                yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(s, pa.float64())], [*batch.schema.names, "quality_score"])

    return docs.mapInArrow(run, StructType([*docs.schema.fields, StructField("quality_score", DoubleType())]))
