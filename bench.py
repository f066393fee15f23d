"""Headline queries at ``$BENCH_SF_DIR`` on ``local[$BENCH_CPUS]``; prints one JSON line."""

from __future__ import annotations

import json
import os
import time
from fractions import Fraction
from pathlib import Path

from pyspark.sql import SparkSession

from rulelattice import catalogue
from rulelattice.operators import levelwise
from rulelattice.operators.integrated import query_sets, with_session_bounds
from rulelattice.operators.ledger import Ledger
from rulelattice.workload import STRATEGIES, load, random_queries, run_session

DIR = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
CPUS = os.environ.get("BENCH_CPUS", "8")
#: Minimal support as a share, by view: stand-ins of the four data sets that the reference reports.
MINING = {"dense_order": Fraction(5, 100), "clicks": Fraction(2, 1000), "basket_part": Fraction(1, 5000), "doc_terms": Fraction(4, 10)}
QUERIES = ("flagship", "kernel_probe", "kernel_bitmap", "integrated_conj", "boolean_nested", "rules_allsplits", "rules_levelwise", "frequent_fpgrowth", "incremental_coverage", "postprocess_rules_on_demand")


def main() -> None:
    spark = (
        SparkSession.builder.master(f"local[{CPUS}]").config("spark.driver.memory", "12g").config("spark.sql.shuffle.partitions", CPUS).config("spark.ui.enabled", "false").config("spark.ui.showConsoleProgress", "false").config("spark.sql.session.timeZone", "UTC").getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    catalogue.flagship(spark, "/root/testdata/sf0.001").count()  # compiles what all share
    seconds: dict[str, float] = {}
    measures: dict[str, float] = {}
    for view, share in MINING.items():
        began = time.time()
        ds, minsup = load(spark, DIR, view, share)
        loaded = time.time()
        ledger = Ledger()
        found = levelwise.frequent_sets(ds, minsup, ledger=ledger)
        seconds[f"mine_{view}"] = round(time.time() - loaded, 3)
        seconds[f"encode_{view}"] = round(loaded - began, 3)
        measures |= {f"{view}_itemsets": len(found), f"{view}_iterations": ledger.total("iterations"), f"{view}_transactions": ds.size, f"{view}_minsup": minsup}
        if view == "dense_order":
            queries = random_queries(catalogue.DENSE_ITEMS, 20, seed=41)
            full = ledger.total("generated")
            points = []
            for q in queries:
                own = Ledger()
                points.append((len(query_sets(ds, with_session_bounds(q, minsup, None), ledger=own)) / len(found), own.total("generated") / full))
            measures["proportionality"] = round(sum(x * y for x, y in points) / sum(x * x for x, _ in points), 3)
            totals = {}
            for strategy, coverage in STRATEGIES:
                began = time.time()
                session = run_session(ds, queries, strategy, minsup, coverage=coverage)
                name = strategy if coverage == "none" else f"{strategy}_{coverage}"
                seconds[f"session20_{name}"] = round(time.time() - began, 3)
                measures[f"session20_{name}_generated"] = session.ledger.total("generated")
                totals[name] = session
            spent, mined = 0.0, totals["postprocess"].ledger.total("generated", 0)
            cut = 0
            for i in range(1, len(queries) + 1):
                spent += totals["integrated"].ledger.total("generated", i)
                if spent > mined:
                    cut = i
                    break
            measures["cutoff_query"] = cut
    for name in QUERIES:
        began = time.time()
        catalogue.queries()[name](spark, DIR).write.format("noop").mode("overwrite").save()
        seconds[name] = round(time.time() - began, 3)
    if (Path(__file__).parent / "rulelattice/llm").exists():
        from rulelattice.llm import registry

        for name, run in registry.queries().items():
            began = time.time()
            run(spark, DIR).write.format("noop").mode("overwrite").save()
            seconds[name] = round(time.time() - began, 3)
    print(json.dumps({"metric": "total seconds of the headline queries", "value": round(sum(seconds.values()), 3), "unit": "sec", "queries": seconds, "sf": DIR.rstrip("/").rsplit("sf", 1)[-1], "measures": measures}))


if __name__ == "__main__":
    main()
