"""Mixing sources to target weights by temperature.

Every source's share of the tokens is raised to one exponent and the results are normalised.  Exponent 1 keeps the
shares, 0 makes all sources equal.  Entropy falls and the largest repetition falls as the exponent grows,
so bisection finds it; one round of it tries GRID exponents at once, in one aggregation over the sources.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from .common import store

#: Exponents of one round and rounds: 32 ** 5 steps over [0, 1].
GRID, ROUNDS = 32, 5
#: Tokens of a block, about, and blocks of a span: no window holds more than one block's documents, one span's blocks or one source's spans.
#: A source of 10 ** 14 tokens has some 80,000 spans.
BLOCK_TOKENS, SPAN_BLOCKS = 20_000, 65_536


def word_count(text: Column) -> Column:
    """Words between white space, as a column."""
    return F.regexp_count(F.coalesce(text, F.lit("")), F.lit(r"[^\x20\x09-\x0D]+")).cast("long")


def source_totals(sized: DataFrame) -> DataFrame:
    return sized.groupBy("source").agg(F.sum("tokens").alias("source_tokens"), F.count(F.lit(1)).alias("source_docs"))


def exponent(sources: DataFrame, entropy: float | None = None, repeats: float | None = None, budget_share: float = 1.0) -> float:
    """The exponent that meets the target.

    entropy: share of the largest possible entropy (0 to 1) the weights must have at least; the largest such
    exponent is taken.  repeats: no source may be read more often than this; the smallest such exponent is taken.
    If no exponent in [0, 1] meets the target, the nearest end is taken.  Sources without tokens weigh nothing.
    """
    if (entropy is None) == (repeats is None):
        raise ValueError("give either entropy or repeats")
    full = sources.filter("source_tokens > 0")
    n, total = full.agg(F.count(F.lit(1)), F.sum("source_tokens")).first()
    if not n:
        return 1.0
    share = F.col("source_tokens") / F.lit(float(total))
    low, high = 0.0, 1.0
    for _ in range(ROUNDS):
        tries = [low + (high - low) * k / GRID for k in range(GRID + 1)]
        sums = []
        for k, a in enumerate(tries):
            power = F.pow(share, F.lit(a))
            sums.append(F.sum(power).alias(f"s{k}"))
            sums.append((F.sum(power * F.log(power)) if entropy is not None else F.max(power / share)).alias(f"m{k}"))
        row = full.agg(*sums).first()
        if entropy is not None:
            # H = log S - sum(x log x) / S, falling as the exponent grows.
            met = [math.log(row[f"s{k}"]) - row[f"m{k}"] / row[f"s{k}"] >= entropy * math.log(n) - 1e-12 for k in range(GRID + 1)]
            k = max((i for i, ok in enumerate(met) if ok), default=0)
            low, high = tries[k], tries[min(k + 1, GRID)]
        else:
            met = [budget_share * row[f"m{k}"] / row[f"s{k}"] <= repeats + 1e-12 for k in range(GRID + 1)]
            k = min((i for i, ok in enumerate(met) if ok), default=GRID)
            low, high = tries[max(k - 1, 0)], tries[k]
    return low if entropy is not None else high


def weights(sources: DataFrame, a: float) -> DataFrame:
    """source, source_tokens, source_docs, weight (the weights sum to 1)."""
    full = sources.filter("source_tokens > 0")
    total = full.agg(F.sum("source_tokens")).first()[0] or 1
    power = F.pow(F.col("source_tokens") / F.lit(float(total)), F.lit(float(a)))
    norm = full.agg(F.sum(power)).first()[0] or 1.0
    return sources.withColumn("weight", F.when(F.col("source_tokens") > 0, power / F.lit(float(norm))).otherwise(F.lit(0.0)))


def mix_sources(docs: DataFrame, *, entropy: float | None = None, repeats: float | None = None, budget_share: float = 1.0, seed: int = 0, id_col: str = "doc_id", text_col: str = "text", source_col: str = "source", tokens: Column | None = None) -> DataFrame:
    """One row per row of docs: id, source, tokens, source_tokens, weight, block, block_rank, start, copies.

    The budget is budget_share times all tokens.  A source's part of it, floor(weight * budget) tokens, is dealt out as
    passes over a permutation of the source: its documents fall into blocks by a keyed hash, the blocks stand in
    the order of another keyed hash (span by span where a source has very many), and the documents of a block in the order of a third.  start is the number of the
    source's tokens before the document in that order.  Every whole pass counts one copy; in the last,
    cut pass a document is taken while start is below what is left of the budget, so a source passes its part by less than
    one document.  Documents without tokens get the whole passes, and the cut one if they stand before its end.

    Null and empty sources are one source, ''.  Null texts are empty.  Rows with the same id and text each stand
    for themselves and share their place.  An empty table gives an empty result.
    """
    counted = (word_count(F.col(text_col)) if tokens is None else tokens).alias("tokens")
    sized = docs.select(F.col(id_col).alias("id"), F.coalesce(F.col(source_col), F.lit("")).alias("source"), counted)
    key = F.concat(F.lit(f"{seed}:"), F.coalesce(F.col("id").cast("string"), F.lit("")))
    sized = store(sized.withColumn("h", F.md5(key)), "mix-sized")
    sources = store(source_totals(sized), "mix-sources")
    a = exponent(sources, entropy, repeats, budget_share)
    total = sources.agg(F.sum("source_tokens")).first()[0] or 0
    weighed = weights(sources, a).withColumn("part", F.floor(F.col("weight") * F.lit(float(total) * budget_share)).cast("long"))
    n_blocks = F.floor(F.col("source_tokens") / BLOCK_TOKENS) + 1
    number = lambda h: F.conv(F.substring(h, 1, 15), 16, 10).cast("long")
    placed = sized.join(weighed, "source").withColumn("n_blocks", n_blocks).withColumn("block", F.pmod(number(F.col("h")), F.col("n_blocks")))
    blocks = placed.groupBy("source", "block", "n_blocks").agg(F.sum("tokens").alias("block_tokens"))
    blocks = blocks.withColumn("o", F.md5(F.concat(F.lit(f"{seed}/"), F.col("block").cast("string")))).withColumn("span", F.pmod(number(F.col("o")), F.floor(F.col("n_blocks") / SPAN_BLOCKS) + 1))
    spans = blocks.groupBy("source", "span").agg(F.sum("block_tokens").alias("span_tokens"), F.count(F.lit(1)).alias("span_blocks"))
    until = Window.partitionBy("source").orderBy("span").rowsBetween(Window.unboundedPreceding, 0)
    spans = spans.select("source", "span", (F.sum("span_tokens").over(until) - F.col("span_tokens")).alias("tokens_before"), (F.sum("span_blocks").over(until) - F.col("span_blocks")).alias("blocks_before"))
    order = Window.partitionBy("source", "span").orderBy("o", "block")
    ordered = blocks.select("source", "span", "block", F.row_number().over(order).cast("long").alias("r"), (F.sum("block_tokens").over(order.rowsBetween(Window.unboundedPreceding, 0)) - F.col("block_tokens")).alias("b"))
    blocks = ordered.join(spans, ["source", "span"]).select("source", "block", (F.col("r") + F.col("blocks_before")).alias("block_rank"), (F.col("b") + F.col("tokens_before")).alias("before"))
    within = Window.partitionBy("source", "block").orderBy("h", F.col("id").asc_nulls_first(), "tokens").rowsBetween(Window.unboundedPreceding, 0)
    ranked = placed.withColumn("inside", F.sum("tokens").over(within) - F.col("tokens")).join(blocks, ["source", "block"])
    start = F.col("before") + F.col("inside")
    size = F.greatest(F.col("source_tokens"), F.lit(1))
    copies = (F.floor(F.col("part") / size) + F.when(start < F.col("part") % size, 1).otherwise(0)).cast("long")
    return ranked.select(F.col("id").alias(id_col), "source", "tokens", "source_tokens", F.col("weight"), "block", "block_rank", start.alias("start"), copies.alias("copies"))


def mixed(docs: DataFrame, **how) -> DataFrame:
    """The rows of docs, each as often as the mixture takes it (not at all, once or more), with all their columns.

    Rows with one id and different texts are all taken as often as the one taken most.  An empty table gives an empty one.
    """
    id_col = how.get("id_col", "doc_id")
    # A row travels as one value, so any names of columns will do.
    whole = docs.select(F.struct(*[F.col(f"`{c}`") for c in docs.columns]).alias("row"))
    taken = mix_sources(docs, **how).groupBy(F.col(id_col).alias("id")).agg(F.max("copies").alias("copies")).filter("copies > 0")
    rows = whole.join(taken, F.col("row")[id_col].eqNullSafe(F.col("id")))
    return rows.select("row", F.explode(F.expr("sequence(1L, copies)"))).select("row.*")
