"""Seeded graph generators as data sources: copied links, and uniform edges."""

from __future__ import annotations

import random

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

SCHEMA = "src bigint, dst bigint"


class _Range(InputPartition):
    def __init__(self, start: int, stop: int):
        self.start, self.stop = start, stop


class CopyModelReader(DataSourceReader):
    """Each node takes degree links: with p_random a random earlier node, else that link of its prototype, an earlier node.

    A node's draws depend on the seed and its number alone, so a link is followed back through prototypes wherever it is asked for: a
    partition makes its own nodes without the others.
    """

    def __init__(self, options: dict):
        self.nodes, self.degree = int(options.get("nodes", 100)), int(options.get("degree", 5))
        self.p, self.seed, self.parts = float(options.get("p_random", 0.1)), int(options.get("seed", 1)), int(options.get("parts", 8))

    def partitions(self):
        step = max(1, -(-self.nodes // self.parts))
        return [_Range(a, min(a + step, self.nodes)) for a in range(0, self.nodes, step)]

    def link(self, node: int, slot: int) -> int:
        while True:
            r = random.Random(self.seed * 1_000_003 + node * 31 + slot)
            prototype = random.Random(self.seed * 7_368_787 + node).randrange(node) if node > 0 else 0
            if node <= self.degree or r.random() < self.p:
                return r.randrange(node) if node else 0
            node = prototype

    def read(self, partition):
        for node in range(max(partition.start, 1), partition.stop):
            for dst in sorted({self.link(node, s) for s in range(self.degree)}):
                yield node, dst


class CopyModelSource(DataSource):
    """format('copy_model'), options nodes, degree, p_random, seed, parts."""

    @classmethod
    def name(cls):
        return "copy_model"

    def schema(self):
        return SCHEMA

    def reader(self, schema):
        return CopyModelReader(self.options)


class UniformReader(DataSourceReader):
    def __init__(self, options: dict):
        self.nodes, self.p = int(options.get("nodes", 100)), float(options.get("p", 0.1))
        self.seed, self.parts = int(options.get("seed", 1)), int(options.get("parts", 8))

    def partitions(self):
        step = max(1, -(-self.nodes // self.parts))
        return [_Range(a, min(a + step, self.nodes)) for a in range(0, self.nodes, step)]

    def read(self, partition):
        for src in range(partition.start, partition.stop):
            r = random.Random(self.seed * 1_000_003 + src)
            for dst in range(self.nodes):
                if r.random() < self.p:
                    yield src, dst


class UniformSource(DataSource):
    """format('uniform_graph'), options nodes, p, seed, parts: each ordered pair is an edge with probability p."""

    @classmethod
    def name(cls):
        return "uniform_graph"

    def schema(self):
        return SCHEMA

    def reader(self, schema):
        return UniformReader(self.options)


def register(spark: SparkSession) -> None:
    spark.dataSource.register(CopyModelSource)
    spark.dataSource.register(UniformSource)


def uniform_edges(spark: SparkSession, nodes: int, p: float = 0.1, seed: int = 1) -> DataFrame:
    """The uniform graph by native functions: pair i of nodes * nodes is an edge if its hash falls below p; the same on any partitioning."""
    draw = F.pmod(F.xxhash64(F.col("id"), F.lit(seed)), F.lit(1_000_000)) < F.lit(int(p * 1_000_000))
    return spark.range(nodes * nodes).filter(draw).select(F.expr(f"id div {nodes}").alias("src"), (F.col("id") % nodes).alias("dst"))


def copy_model_on(nodes: DataFrame, degree: int = 5, p: float = 0.1, seed: int = 1) -> DataFrame:
    """The copy model on nodes that a table gives (one column of numbers from 0): each row makes its own links, in the task that reads it."""

    def links(batches):
        model = CopyModelReader({"degree": degree, "p_random": p, "seed": seed})
        for batch in batches:
            made = [(v, dst) for v in map(int, batch.iloc[:, 0]) if v > 0 for dst in sorted({model.link(v, k) for k in range(degree)})]
            yield pd.DataFrame(made, columns=["src", "dst"])

    return nodes.mapInPandas(links, SCHEMA)


def uniform_on(nodes: DataFrame, p: float = 0.1, seed: int = 1) -> DataFrame:
    """Uniform graphs on the groups of a table (columns node, group): each ordered pair of nodes of a group is an edge with probability p.

    A node's draws depend on the seed and its number alone, one for each node of its group in order."""

    def links(group: pd.DataFrame) -> pd.DataFrame:
        ids = sorted(map(int, group.node))
        made = []
        for src in ids:
            r = random.Random(seed * 1_000_003 + src)
            made += [(src, dst) for dst in ids if r.random() < p]
        return pd.DataFrame(made, columns=["src", "dst"])

    return nodes.groupBy("group").applyInPandas(links, SCHEMA)


def uniform_on_native(nodes: DataFrame, p: float = 0.1, seed: int = 1) -> DataFrame:
    """As uniform_on by native functions: a pair is an edge if its hash falls below p."""
    draw = F.pmod(F.xxhash64("src", "dst", F.lit(seed)), F.lit(1_000_000)) < F.lit(int(p * 1_000_000))
    return nodes.selectExpr("node as src", "group").join(nodes.selectExpr("node as dst", "group"), "group").filter(draw).select("src", "dst")
