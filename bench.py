"""Headline queries at $BENCH_SF_DIR on local[$BENCH_CPUS]; prints one JSON line.

A first run that is not counted starts the JVM and the Python workers. ``*_real`` runs are those of the published
table: 5 %, five items, gap 10, the partner miner at 70 % of it. ``frontier_*`` is the engine for databases beyond planner.LOCAL_ROWS.
"""

from __future__ import annotations

import json
import os
import sys
import time
from pathlib import Path

sys.path.insert(0, str(Path(__file__).resolve().parent))


def main() -> None:
    from pyspark.sql import SparkSession

    from negseq.operators import baselines, growth, matching, measures
    from negseq.operators import sequences as S
    from negseq.operators.growth import Options

    d, cpus = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1"), os.environ.get("BENCH_CPUS", "8")
    spark = SparkSession.builder.master(f"local[{cpus}]").config("spark.sql.shuffle.partitions", cpus).config("spark.driver.memory", "16g").config("spark.ui.enabled", "false").config("spark.sql.session.timeZone", "UTC").getOrCreate()
    spark.sparkContext.setLogLevel("ERROR")

    def grow(view: str, sigma: str, engine: str = "auto", **kw):
        return lambda: growth.mine(S.VIEWS[view](spark, d), sigma, Options(**kw), engine=engine)

    def partner(view: str, sigma: str, ratio: float, max_items: int = 3):
        return lambda: baselines.mine_partner(S.VIEWS[view](spark, d), sigma, ratio, max_items)

    runs = {
        "growth_priority_gap3": grow("priority", "0.5", maxgap=3),
        "growth_priority_gap10": grow("priority", "0.5", maxgap=10),
        "growth_priority_free": grow("priority", "0.5"),
        "partner_priority_100": partner("priority", "0.5", 1.0),
        "partner_priority_070": partner("priority", "0.5", 0.7),
        "partner_priority_020": partner("priority", "0.5", 0.2),
        "growth_words_gap3": grow("words", "0.3", maxgap=3),
        "growth_tags_gap3": grow("tags", "0.5", maxgap=3),
        "growth_basket_gap3": grow("basket_brand", "0.5", maxgap=3),
        "growth_priority_real": grow("priority", "0.05", maxgap=10, max_items=5),
        "partner_priority_real": partner("priority", "0.05", 0.7, 5),
        "growth_clicks_real": grow("clicks", "0.05", maxgap=10, max_items=4),
        "frontier_priority_gap3": grow("priority", "0.5", "frontier", maxgap=3),
        "support_scan": lambda: matching.support(S.nested(S.days(spark, d)), ["click !error click", "click !(error view) signup", "view !click purchase !error view"]),
    }
    grow("turns", "0.2", maxgap=3)().count()
    seconds, patterns, status = {}, {}, {}
    for name, run in runs.items():
        began = time.perf_counter()
        with measures.time_limit(spark, 120) as state:
            patterns[name] = run().count()
        seconds[name], status[name] = round(time.perf_counter() - began, 3), state["status"]
    late = [name for name, s in status.items() if s != "done"]
    print(json.dumps({"metric": "headline_seconds", "value": round(sum(seconds.values()), 3), "unit": "sec", "queries": seconds, "patterns": patterns, "stopped": late, "sf": d.rstrip("/").rsplit("sf", 1)[-1]}))
    spark.stop()


if __name__ == "__main__":
    main()
