"""Experiment runs: real-graph stand-ins, time against edges, patterns and rules, and slow queries.

python -m twigmine.workloads NAME [SF_DIR] prints the rows of a run.
"""

from __future__ import annotations

import sys
import time
from collections.abc import Callable

from pyspark.sql import SparkSession

from .graph import Graph, load
from .model.query import TreeQuery, parse_pattern
from .operators import rules
from .operators.miner import Mined, mine
from .plans.twig import support_table
from .sources.datagraphs import GRAPHS
from .sources.synthetic import register

#: Graph, threshold and largest tree of each stand-in.
STAND_INS = {"food_web": ("supply_chain", 25, 4), "proteins": ("embedding_neighbors", 10, 4), "citations": ("customer_part", 5, 3), "complete": ("nation_trade", 25, 3), "links": ("page_links", 5, 4)}


def mine_stand_in(spark: SparkSession, sf_dir: str, name: str, max_nodes: int | None = None) -> Mined:
    graph, minsup, size = STAND_INS[name]
    g = GRAPHS[graph](spark, sf_dir).persisted()
    try:
        return mine(g, minsup, max_nodes or size)
    finally:
        g.release()


def _row(name: str, g: Graph, minsup: int, found: Mined) -> dict:
    m = found.metrics
    return {"graph": name, "edges": g.edges.count(), "minsup": minsup, "seconds": round(m.wall_s, 2), "patterns": m.patterns, "classes": m.classes, "support_queries": m.support_queries, "seconds_per_pattern": round(m.wall_s / max(m.patterns, 1), 5), "slope": m.seconds_per_pattern(), **{f"pruned_{k}": v for k, v in m.pruned.items()}}


def web_graphs(spark: SparkSession, sf_dir: str, sizes=(50, 100, 200), minsups=(4, 10, 25), max_nodes: int = 3) -> list[dict]:
    """Time against edges on copied-link graphs of degree 5 with one link in ten at random."""
    register(spark)
    out = []
    for n in sizes:
        g = load(spark.read.format("copy_model").options(nodes=n, degree=5, p_random=0.1, seed=11).load()).persisted()
        out += [_row(f"copy_model_{n}", g, k, mine(g, k, max_nodes)) for k in minsups]
        g.release()
    return out


def uniform_graphs(spark: SparkSession, sf_dir: str, minsups=(10, 25), max_nodes: int = 3) -> list[dict]:
    """Time against patterns on three uniform graphs; seconds per pattern should not depend on graph or threshold."""
    out = []
    for name in ("key_step_3d_22", "key_step_3d_51", "key_step_3d"):
        g = GRAPHS[name](spark, sf_dir).persisted()
        out += [_row(name, g, k, mine(g, k, max_nodes)) for k in minsups]
        g.release()
    return out


def rule_times(spark: SparkSession, sf_dir: str, minconfs=("0.2", "0.5"), max_nodes: int = 4, minsup: int = 25) -> list[dict]:
    """Time against rules on a uniform graph of 33 nodes, for left sides of growing size, at two confidences."""
    register(spark)
    g = load(spark.read.format("uniform_graph").options(nodes=33, p=0.1, seed=5).load()).persisted()
    store = mine(g, minsup, max_nodes, strategy="cube").tables
    out = []
    for text in ("x(y)", "x(#a,z)", "x(y,z)", "x(y(z))", "x(#a,y,z)"):
        p = parse_pattern(text).pattern
        lhs = TreeQuery(p.free, p)
        for c in minconfs:
            began, counts = time.perf_counter(), rules.FoldCounts()
            n, queries = rules.count_rules(rules.mine_rules(store, lhs, c, g, counts=counts)).first()
            took = time.perf_counter() - began
            out.append({"lhs": text, "minconf": c, "rules": n, "rhs_queries": queries, "seconds": round(took, 3), "folds_made": counts.made, "folds_legal": counts.legal, "folds_kept": counts.kept})
    g.release()
    for c in minconfs:
        own = [r for r in out if r["minconf"] == c and "seconds" in r]
        out.append({"minconf": c, "seconds_per_rule": slope([(r["rules"], r["seconds"]) for r in own]), "seconds_per_rhs_query": slope([(r["rhs_queries"], r["seconds"]) for r in own])})
    return out


def slope(points: list[tuple[float, float]]) -> float | None:
    """Least-squares slope of the second values over the first."""
    k = len(points)
    mx, my = (sum(p[i] for p in points) / max(k, 1) for i in (0, 1))
    spread = sum((x - mx) ** 2 for x, _ in points)
    return sum((x - mx) * (y - my) for x, y in points) / spread if spread else None


def slow_queries(spark: SparkSession, sf_dir: str, seconds: float = 120) -> list[dict]:
    """Patterns of four to six nodes on a dense cyclic graph, by the plain join and by the fold; the join is left out where its size forbids it."""
    g = GRAPHS["key_step_30d"](spark, sf_dir).persisted()
    edges = g.edges.count()
    out = []
    for text in ("x(y(z))", "x(y,z(w))", "#a(x(y(z)))", "x1(x2(x3), x4(x5, x6))", "#a(?(?(x)), y(z))"):
        p = parse_pattern(text).pattern
        for strategy in ("fold", "expand"):
            if strategy == "expand" and (edges / 100) ** (p.size - 1) * 100 > 5e7:
                out.append({"pattern": text, "strategy": strategy, "seconds": None, "freq": None})
                continue
            began = time.perf_counter()
            total = support_table(g, p, strategy=strategy).groupBy().sum("freq").first()[0]
            out.append({"pattern": text, "strategy": strategy, "seconds": round(time.perf_counter() - began, 2), "freq": total})
    g.release()
    return out


def ablations(spark: SparkSession, sf_dir: str, minsup: int = 10, max_nodes: int = 3) -> list[dict]:
    """Support queries and time with neither, one and both ways of leaving out equivalent patterns, and by grouping sets."""
    g = GRAPHS["key_step_3d_22"](spark, sf_dir).persisted()
    out = []
    for how in ({"dedup": "none", "order": "double"}, {"dedup": "redundancy"}, {"dedup": "canonical"}, {"dedup": "full"}, {"strategy": "cube"}, {"strategy": "expand"}):
        out.append(_row(str(how), g, minsup, mine(g, minsup, max_nodes, **how)))
    g.release()
    return out


RUNS: dict[str, Callable] = {"web_graphs": web_graphs, "uniform_graphs": uniform_graphs, "rule_times": rule_times, "slow_queries": slow_queries, "ablations": ablations}
RUNS |= {k: lambda s, d, k=k: [_row(k, GRAPHS[STAND_INS[k][0]](s, d), STAND_INS[k][1], mine_stand_in(s, d, k))] for k in STAND_INS}


def main(name: str, sf_dir: str = "/root/testdata/sf0.01") -> None:
    spark = SparkSession.builder.master("local[8]").config("spark.sql.shuffle.partitions", "8").config("spark.driver.memory", "8g").config("spark.ui.enabled", "false").config("spark.ui.showConsoleProgress", "false").config("spark.sql.session.timeZone", "UTC").getOrCreate()
    spark.sparkContext.setLogLevel("ERROR")
    for row in RUNS[name](spark, sf_dir):
        print(row, flush=True)


if __name__ == "__main__":
    main(*sys.argv[1:])
