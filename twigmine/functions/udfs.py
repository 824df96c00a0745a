"""Functions for SQL users: canonical keys, fold maps, ratios, bounded counts."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import Column, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import ArrayType, BooleanType, IntegerType, LongType, StringType, StructField, StructType

from ..model.contain import covers_free, fold_maps
from ..model.pattern import Pattern, pattern_key, pattern_of_key


@F.pandas_udf(StringType())
def pattern_key_udf(levels: pd.Series, marks: pd.Series) -> pd.Series:
    """Canonical key of a pattern given as levels ARRAY<INT> and marks STRING."""
    return pd.Series([None if v is None or m is None else pattern_key(Pattern(tuple(int(x) for x in v), m)) for v, m in zip(levels, marks, strict=True)])


@F.pandas_udf(BooleanType())
def redundant_udf(levels: pd.Series, marks: pd.Series) -> pd.Series:
    return pd.Series([None if v is None or m is None else Pattern(tuple(int(x) for x in v), m).has_redundancy() for v, m in zip(levels, marks, strict=True)])


@F.udtf(returnType=StructType([StructField("fold", ArrayType(IntegerType())), StructField("rho", ArrayType(IntegerType())), StructField("legal", BooleanType())]))
class FoldMaps:
    """One row per fold map of the lhs pattern into the rhs pattern, both by key."""

    def eval(self, lhs_key: str, rhs_key: str):
        if lhs_key is None or rhs_key is None:
            return
        p, q = pattern_of_key(lhs_key), pattern_of_key(rhs_key)
        numbers = {v: k for k, v in enumerate(q.pins)}
        for f in fold_maps(p, q):
            yield list(f), [numbers[f[i]] for i in p.pins], covers_free(f, q, p)


@F.udtf(returnType=StructType([StructField("pattern_key", StringType()), StructField("pins", ArrayType(StringType())), StructField("freq", LongType())]))
class MineSmall:
    """mine_tree_patterns(TABLE(edges) WITH SINGLE PARTITION, minsup, max_nodes) for a graph that one task holds: brute force over its patterns."""

    def __init__(self):
        self.edges, self.minsup, self.most = set(), 1, 1

    def eval(self, row, minsup: int, max_nodes: int):
        self.edges.add((row[0], row[1]))
        self.minsup, self.most = minsup, max_nodes

    def terminate(self):
        from collections import Counter

        from ..model.pattern import all_marks
        from ..model.shape import shapes

        nodes = {x for e in self.edges for x in e}
        after: dict = {}
        for a, b in self.edges:
            after.setdefault(a, []).append(b)
        for levels in shapes(self.most):
            for p in all_marks(levels, "full"):
                rows = [(x,) for x in nodes]
                for i in range(1, p.size):
                    rows = [(*r, y) for r in rows for y in after.get(r[p.parent[i]], ())]
                visible = [i for i in range(p.size) if p.marks[i] != "e"]
                distinct = {tuple(r[i] for i in visible) for r in rows}
                where = [visible.index(i) for i in p.pins]
                for pins, freq in sorted(Counter(tuple(r[k] for k in where) for r in distinct).items(), key=str):
                    if freq >= self.minsup:
                        yield p.refined(), [str(x) for x in pins], freq


def distinct_at_least(k: int):
    """Aggregate: whether a group has k different values, counted no further than k."""

    @F.pandas_udf(BooleanType())
    def run(values: pd.Series) -> bool:
        seen = set()
        for v in values:
            if v is not None and v == v:
                seen.add(v)
                if len(seen) >= k:
                    return True
        return False

    return run


def bind_pins(pins: str = "pins", rho: str = "rho") -> Column:
    return F.expr(f"transform({rho}, i -> {pins}[i])")


def exact_ratio(freq: str = "freq", lhs_freq: str = "lhs_freq") -> Column:
    return (F.col(freq).cast("decimal(20,0)") / F.col(lhs_freq).cast("decimal(20,0)")).cast("decimal(38,18)")


def cosine(a: str, b: str) -> Column:
    dot = lambda x, y: f"aggregate(zip_with({x}, {y}, (p, q) -> cast(p as double) * q), 0D, (s, v) -> s + v)"
    return F.expr(f"{dot(a, b)} / sqrt({dot(a, a)} * {dot(b, b)})")


def register(spark: SparkSession) -> None:
    spark.udf.register("pattern_key", pattern_key_udf)
    spark.udf.register("redundant", redundant_udf)
    spark.udtf.register("fold_maps", FoldMaps)
    spark.udtf.register("mine_tree_patterns", MineSmall)
