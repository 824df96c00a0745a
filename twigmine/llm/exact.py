"""Exact duplicates by progressive refinement: length, then prefix hash, then full hash."""

from __future__ import annotations

import string

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import store

PREFIX = 64
#: What is broadcast of shared keys: the different values of a hash with so many values, 8 bytes each, so 8 MB at any size of the corpus.
SIEVE = 1 << 20


def lowered(text: Column) -> Column:
    """Text with A-Z lower-cased; null is empty.

    Texts of ASCII alone, as many bytes as characters, take Spark's quick lower, which does the same there."""
    text = F.coalesce(text.cast("string"), F.lit(""))
    return F.when(F.octet_length(text) == F.length(text), F.lower(text)).otherwise(F.translate(text, string.ascii_uppercase, string.ascii_lowercase))


def refine_keys(text: Column) -> tuple[Column, Column]:
    """Length and prefix hash of a text: lower-casing keeps the length, and a prefix needs no more than itself lowered."""
    text = F.coalesce(text.cast("string"), F.lit(""))
    return F.length(text), F.xxhash64(lowered(F.substring(text, 1, PREFIX)))


def sieve_of(text: Column) -> Column:
    return F.pmod(F.xxhash64(*refine_keys(text)), F.lit(SIEVE))


def shared_sieve(docs: DataFrame, text_col: str) -> DataFrame:
    """sieve: where texts stand that share their length and their prefix with another one; at most SIEVE rows.

    Lengths that one row has end there; then (length, prefix hash) keys that one row has.
    """
    n, p = refine_keys(F.col(text_col))
    keys = store(docs.select(n.alias("n"), p.alias("p")), "exact-keys")
    # Lengths stand by their remainder: below SIEVE characters each by itself.
    keys = keys.withColumn("m", F.pmod("n", F.lit(SIEVE)))
    lengths = store(keys.groupBy("m").count().filter("count > 1").select("m"), "exact-lengths")
    shared = keys.join(F.broadcast(lengths), "m", "left_semi").groupBy("n", "p").count().filter("count > 1")  # at most SIEVE rows
    return store(shared.select(F.pmod(F.xxhash64("n", "p"), F.lit(SIEVE)).alias("sieve")).distinct(), "exact-sieve")


def hashed_rows(docs: DataFrame, id_col: str, text_col: str, every_digest: bool, sieve: DataFrame) -> DataFrame:
    """id, shared, digest (binary) of every row: the one full reading."""
    placed = docs.select(F.col(id_col).alias("id"), sieve_of(F.col(text_col)).alias("sieve"), lowered(F.col(text_col)).alias("t"))
    marked = placed.join(F.broadcast(sieve.withColumn("shared", F.lit(True))), "sieve", "left")  # at most SIEVE rows
    wanted = F.lit(True) if every_digest else F.col("shared")
    return store(marked.select("id", F.coalesce("shared", F.lit(False)).alias("shared"), F.when(wanted, F.unhex(F.sha2("t", 256))).alias("digest")), "exact-hashes")


def groups_of(hashed: DataFrame) -> DataFrame:
    """digest, keep_id, group_size of digests that several rows have."""
    return store(hashed.filter("shared").groupBy("digest").agg(F.max("id").alias("keep_id"), F.count(F.lit(1)).alias("group_size")).filter("group_size > 1"), "exact-groups")


def exact_duplicates(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", every_digest: bool = False) -> DataFrame:
    """One row per row of docs: id, keep_id, group_size, kept, digest (hexadecimal SHA-256).

    Texts are equal when identical after lower-casing A-Z; null counts as empty.  The row with the
    largest id stays (null ids are smallest).  Rows repeated with id and text each come back, with one verdict, and each counts in
    group_size.  An empty table gives an empty result; further columns are not read.  Ids may be of any type that has an order.
    digest is null for texts that one row has, unless every_digest.

    A first reading leaves length and prefix hash of each row; what they share becomes a sieve of fixed size, by which the second
    reading hashes the full content of the rows that may have an equal.  Texts that the sieve lets through in vain
    cost their hash and nothing else.  Content is never shuffled, and digests are joined to their groups in a join that AQE can split.
    """
    hashed = hashed_rows(docs, id_col, text_col, every_digest, shared_sieve(docs, text_col))
    found = hashed.filter("shared").join(groups_of(hashed), "digest", "left").select("id", "digest", "keep_id", "group_size")
    rows = found.unionByName(hashed.filter("not shared").select("id", "digest"), allowMissingColumns=True)
    alone = F.col("group_size").isNull()
    keep = F.when(alone, F.col("id")).otherwise(F.col("keep_id"))
    digest = F.col("digest") if every_digest else F.when(~alone, F.col("digest"))
    return rows.select(F.col("id").alias(id_col), keep.alias("keep_id"), F.coalesce("group_size", F.lit(1)).cast("long").alias("group_size"), F.col("id").eqNullSafe(keep).alias("kept"), F.lower(F.hex(digest)).alias("digest"))


def keep_exact(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """The rows of docs that stay, with all their columns; of rows that agree in id and text one stays.  Null texts are empty.

    Rows that share neither length nor prefix with another one are passed on where they are read.  The others are moved once, by
    digest and id, rows that agree in both falling together before; there they meet the verdicts, which are narrow.
    Any names of columns will do: a row travels as one value.
    """
    sieve = shared_sieve(docs, text_col)
    hashed = hashed_rows(docs, id_col, text_col, False, sieve)
    id_text = lambda c: F.concat(F.when(c.isNull(), "-").otherwise("+"), F.coalesce(c.cast("string"), F.lit("")))
    kept = hashed.filter("shared").groupBy("digest").agg(F.max("id").alias("id")).select(F.concat_ws(":", F.hex("digest"), id_text(F.col("id"))).alias("place"))
    whole = docs.select(F.struct(*[F.col(f"`{c}`") for c in docs.columns]).alias("row"))
    marked = whole.withColumn("sieve", sieve_of(F.col("row")[text_col])).join(F.broadcast(sieve.withColumn("shared", F.lit(True))), "sieve", "left")  # at most SIEVE rows
    place = F.concat_ws(":", F.upper(F.sha2(lowered(F.col("row")[text_col]), 256)), id_text(F.col("row")[id_col]))
    once = marked.filter("shared").select(place.alias("place"), "row").groupBy("place").agg(F.first("row").alias("row"))
    return once.join(kept.hint("merge"), "place", "left_semi").select("row.*").union(marked.filter("shared is null").select("row.*"))
