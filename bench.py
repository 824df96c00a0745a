"""Headline queries at $BENCH_SF_DIR on local[$BENCH_CPUS]; one JSON line."""

from __future__ import annotations

import json
import os
import sys
import time

from pyspark.sql import SparkSession

from twigmine import queries
from twigmine.operators import rules
from twigmine.operators.miner import mine
from twigmine.sources.datagraphs import GRAPHS

HEADLINE = ["match_chain4", "sup_competitor", "sup_repeated_pin", "sup_fork", "sup_six_nodes", "sup_hidden_chain", "rule_hub", "rule_depth_root", "rule_depth_below", "rule_folded", "rule_middle_hub", "rule_hidden_branch", "rule_edge_share_page_links", "rule_sparsity_customer_part"]


def main() -> None:
    sf_dir = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
    cpus = os.environ.get("BENCH_CPUS", str(os.cpu_count()))
    spark = SparkSession.builder.master(f"local[{cpus}]").config("spark.sql.shuffle.partitions", cpus).config("spark.driver.memory", "8g").config("spark.ui.enabled", "false").config("spark.ui.showConsoleProgress", "false").config("spark.sql.session.timeZone", "UTC").getOrCreate()
    spark.sparkContext.setLogLevel("ERROR")
    times: dict[str, float] = {}

    def timed(name: str, f):
        began = time.perf_counter()
        try:
            return f()
        finally:
            times[name] = round(time.perf_counter() - began, 3)

    timed("warm_up", lambda: queries.QUERIES["stats_page_links"](spark, sf_dir).collect())
    for name in HEADLINE:
        timed(name, lambda q=name: queries.QUERIES[q](spark, sf_dir).write.format("noop").mode("overwrite").save())
    notes: dict[str, float] = {}
    g = GRAPHS["page_links"](spark, sf_dir).persisted()
    for minsup in (25, 10):
        for strategy in ("fold", "cube"):
            found = timed(f"mine_{strategy}_size3_minsup{minsup}", lambda m=minsup, s=strategy: mine(g, m, 3, strategy=s))
            notes[f"patterns_{strategy}_minsup{minsup}"] = found.metrics.patterns
            notes[f"seconds_per_pattern_{strategy}_minsup{minsup}"] = round(found.metrics.wall_s / max(found.metrics.patterns, 1), 5)
    small = GRAPHS["key_step_3d_22"](spark, sf_dir).persisted()
    base = timed("mine_for_rules", lambda: mine(small, 25, 3, strategy="cube"))
    for minconf in ("0.2", "0.5"):
        n = timed(f"rules_minconf{minconf}", lambda c=minconf: rules.mine_rules(base.tables, queries.RULE_LHS, c, small).count())
        notes[f"rules_{minconf}"] = n
        notes[f"seconds_per_rule_{minconf}"] = round(times[f"rules_minconf{minconf}"] / max(n, 1), 5)
    total = round(sum(v for k, v in times.items() if k != "warm_up"), 3)
    print(json.dumps({"metric": "headline_total", "value": total, "unit": "sec", "queries": times, "sf": os.path.basename(sf_dir.rstrip("/")), "cpus": int(cpus), "notes": notes}))
    spark.stop()


if __name__ == "__main__":
    sys.exit(main())
