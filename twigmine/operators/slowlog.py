"""Log of support queries: each pattern counted by itself, with its time, rows and largest support."""

from __future__ import annotations

import time
from collections.abc import Iterable

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..graph import Graph
from ..model.pattern import Pattern
from ..plans.twig import support_table


def slow_log(g: Graph, patterns: Iterable[Pattern], minsup: int = 1, strategy: str = "fold") -> DataFrame:
    """pattern_key, seconds, n_rows, most, total of each pattern's support table, slowest first; one row per pattern on the driver."""
    out = []
    for p in patterns:
        began = time.perf_counter()
        r = support_table(g, p, minsup=minsup, strategy=strategy).agg(F.count(F.lit(1)), F.max("freq"), F.sum("freq")).first()
        out.append((p.refined(), time.perf_counter() - began, r[0], r[1], r[2]))
    rows = g.spark.createDataFrame(out, "pattern_key string, seconds double, n_rows bigint, most bigint, total bigint")
    return rows.orderBy(F.desc("seconds"))
