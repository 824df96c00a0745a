"""Document fingerprints: a homomorphic multiset hash of the paragraphs.

A paragraph hashes to a wide vector; a document's fingerprint is the sum of its paragraphs' vectors, each number modulo a power
of two.  Order doesn't matter, and paragraphs can be added and taken away without the text.  A vector has two parts:
EQUAL numbers modulo 2**64 from a cryptographic hash of the paragraph, which tell multisets of paragraphs apart, and LIKE numbers
modulo 2**32, into which the paragraph's word triples are counted with random signs, whose differences tell how alike two
multisets of triples are.  A paragraph is a line with a word in it, white space at its ends left out.
"""

from __future__ import annotations

import hashlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import mix, pieces, text_bytes, width, word_hashes, word_spans

EQUAL, LIKE, RUN = 8, 256, 3
_LINE = 10


def paragraph_vectors(texts: list[str]) -> np.ndarray:
    """One fingerprint per text: uint32 array of 2 * EQUAL + LIKE (the first are 64-bit numbers, low half first)."""
    out = np.zeros((len(texts), 2 * EQUAL + LIKE), np.uint32)
    sums = np.zeros((len(texts), EQUAL), np.uint64)
    data, offsets = text_bytes(pa.array(texts, pa.string()))
    paragraphs = [[q for p in t.split("\n") if (q := p.strip(" \t\n\v\f\r"))] for t in texts]
    counts = np.array([len(p) for p in paragraphs], np.int64)
    if counts.sum():
        digests = b"".join(hashlib.blake2b(p.encode(), digest_size=8 * EQUAL).digest() for ps in paragraphs for p in ps)
        rows = np.frombuffer(digests, "<u8").reshape(-1, EQUAL)
        full = counts > 0
        sums[full] = np.add.reduceat(rows, (np.cumsum(counts) - counts)[full], axis=0)
    out[:, : 2 * EQUAL] = sums.astype("<u8").view(np.uint32).reshape(len(texts), 2 * EQUAL)
    starts, ends, first = word_spans(data, offsets)
    if len(starts):
        words = word_hashes(data, starts, ends)
        owner = np.repeat(np.arange(len(texts)), np.diff(first))
        # A triple doesn't reach over a line end: shorter runs at the paragraph's start count as they are.
        lines = np.cumsum(np.append(0, data == _LINE))[starts] + owner.astype(np.int64) * (len(data) + 1)
        h = mix(words)
        for back in range(1, RUN):
            same = np.zeros(len(words), bool)
            same[back:] = lines[back:] == lines[:-back]
            h[same] += mix(words[np.flatnonzero(same) - back] * np.uint64(2 * back + 1))
        h = mix(h)
        lane = owner * LIKE + (h % np.uint64(LIKE)).astype(np.int64)
        sign = 1.0 - 2.0 * ((h >> np.uint64(40)) & np.uint64(1)).astype(np.float64)
        out[:, 2 * EQUAL :] = np.bincount(lane, sign, len(texts) * LIKE).reshape(len(texts), LIKE).astype(np.int64).astype(np.uint32)
    return out


def add(a: bytes, b: bytes, times: int = 1) -> bytes:
    """Fingerprint of the union of two multisets of paragraphs (times=-1: of the difference)."""
    x, y = np.frombuffer(a, "<u4"), np.frombuffer(b, "<u4")
    wide = x[: 2 * EQUAL].view("<u8") + np.uint64(times % 2**64) * y[: 2 * EQUAL].view("<u8")
    return wide.astype("<u8").tobytes() + (x[2 * EQUAL :] + np.uint32(times % 2**32) * y[2 * EQUAL :]).astype("<u4").tobytes()


def likeness(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """How alike the counted triples of rows of fingerprints are, 0 to 1: their estimated cosine, 1 for equal fingerprints."""
    x, y = (v[:, 2 * EQUAL :].view(np.int32).astype(np.float64) for v in (np.ascontiguousarray(a), np.ascontiguousarray(b)))
    norm = np.sqrt((x * x).sum(1) * (y * y).sum(1))
    cosine = np.divide((x * y).sum(1), norm, out=np.zeros(len(x)), where=norm > 0)
    return np.where((a == b).all(1), 1.0, np.clip(cosine, 0.0, 1.0))


def fingerprint(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """id and fingerprint (binary) for every row; null texts are empty, the empty text has the zero fingerprint."""
    kind = docs.select(id_col).schema[0].dataType.simpleString()

    def run(batches):
        for whole in batches:
            for batch in pieces(whole, "text", 1_000_000):
                rows = paragraph_vectors([t or "" for t in batch.column("text").to_pylist()])
                yield pa.RecordBatch.from_arrays([batch.column("id"), pa.array([r.tobytes() for r in rows], pa.binary())], ["id", "fingerprint"])

    rows = docs.selectExpr(f"`{id_col}` as id", f"cast(`{text_col}` as string) as text")
    return rows.mapInArrow(run, f"id {kind}, fingerprint binary").withColumnRenamed("id", id_col)


def with_next(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Rows in runs by descending id, each run followed by the row that comes next: run, id, text, guest.

    Ids are cut into as many ranges as there are shuffle partitions at quantiles of the ids.  Every range's first row
    also goes to the range before it as a guest, the very first to the last: as many further rows as there are ranges.  The only texts moved are
    the rows, once.  Rows with one id follow each other by their text; null ids come last.
    """
    spark = docs.sparkSession
    n = width(spark)
    rows = docs.select(F.col(id_col).cast("long").alias("id"), F.coalesce(F.col(text_col).cast("string"), F.lit("")).alias("text"))
    # The lowest id is what null stands for in the order only.
    rank = F.coalesce(F.col("id"), F.lit(-(2**63)))
    marks = rows.agg(F.percentile_approx(rank, [k / n for k in range(1, n)] or [0.5], 1000)).first()[0] or []
    marks = sorted(set(marks), reverse=True)
    run = F.size(F.filter(F.array(*[F.lit(m).cast("long") for m in marks]), lambda m: rank < m))
    placed = rows.withColumn("run", run)
    heads = placed.groupBy("run").agg(F.max(F.struct(rank.alias("r"))).alias("h")).orderBy("run").collect()
    if not heads:
        return placed.select("run", "id", "text", F.lit(False).alias("guest"))
    runs = [r.run for r in heads]
    before = {heads[k].run: runs[k - 1] for k in range(len(runs))}
    firsts = {r.run: r.h.r for r in heads}
    to = F.create_map(*[F.lit(x) for k, v in before.items() for x in (k, v)])
    first_of = F.create_map(*[F.lit(x) for k, v in firsts.items() for x in (k, v)])
    is_head = (rank == first_of[F.col("run")])
    # The first of rows with the head's id is the one with the largest text; the others are guests too and stay unused.
    place = lambda r, g: F.struct(r.cast("int").alias("run"), F.lit(g).alias("guest"))
    own = place(F.col("run"), False)
    places = F.when(is_head, F.array(own, place(to[F.col("run")], True))).otherwise(F.array(own))
    dealt = placed.select("id", "text", F.explode(places).alias("p")).select("p.run", "id", "text", "p.guest")
    return dealt.repartitionById(n, "run").sortWithinPartitions("run", "guest", F.col("id").desc_nulls_last(), F.col("text").desc())


def edited(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """For every row: id, n_chars, edited_sha256, fingerprint, edited_fingerprint (binary), near_edited, near_next.

    The edited text has its last floor(n_chars / 2) code points replaced by the first as many (or all) of the next row's text, by
    descending id, after the last the first (rows with one id by descending text).  A row alone is its own next.
    """

    def run(batches):
        held = None  # the last row, whose next isn't known yet
        names = ["id", "n_chars", "edited_sha256", "fingerprint", "edited_fingerprint", "near_edited", "near_next"]
        for whole in batches:
            for batch in pieces(whole, "text", 1_000_000):
                rows = list(zip(*(batch.column(c).to_pylist() for c in ("run", "guest", "id", "text")), strict=True))
                chain = ([held] if held else []) + rows
                held = chain[-1]
                pairs = [(a, b) for a, b in zip(chain, chain[1:], strict=False) if a[0] == b[0] and not a[1]]
                if not pairs:
                    continue
                own = [a[3] for a, _ in pairs]
                after = [b[3] for _, b in pairs]
                made = [t[: len(t) - len(t) // 2] + u[: len(t) // 2] for t, u in zip(own, after, strict=True)]
                # Texts that follow each other are hashed once.
                last = [k for k in range(len(pairs)) if k + 1 == len(pairs) or pairs[k][1] is not pairs[k + 1][0]]
                all_fp = paragraph_vectors(own + [after[k] for k in last])
                fp = all_fp[: len(own)]
                next_fp = np.empty_like(fp)
                next_fp[:-1] = fp[1:]
                next_fp[last] = all_fp[len(own) :]
                made_fp = paragraph_vectors(made)
                yield pa.RecordBatch.from_arrays(
                    [
                        pa.array([a[2] for a, _ in pairs], pa.int64()), pa.array([len(t) for t in own], pa.int64()),
                        pa.array([hashlib.sha256(t.encode()).hexdigest() for t in made], pa.string()),
                        pa.array([r.tobytes() for r in fp], pa.binary()), pa.array([r.tobytes() for r in made_fp], pa.binary()),
                        pa.array(likeness(fp, made_fp), pa.float64()), pa.array(likeness(fp, next_fp), pa.float64()),
                    ],
                    names,
                )

    return with_next(docs, id_col, text_col).mapInArrow(run, "id bigint, n_chars bigint, edited_sha256 string, fingerprint binary, edited_fingerprint binary, near_edited double, near_next double").withColumnRenamed("id", id_col)
