"""Headline queries at $BENCH_SF_DIR on local[$BENCH_CPUS]; prints one JSON line."""

from __future__ import annotations

import json
import os
import sys
import time
from pathlib import Path

sys.path.insert(0, str(Path(__file__).resolve().parent))

from pyspark.sql import SparkSession

from motifprune.operators import counting, metrics
from motifprune.operators.frontier import match
from motifprune.plans.pattern import CATALOGUE, WORKLOAD
from motifprune.shipping import ship
from motifprune.sources.graphs import Graph

SF_DIR, CPUS = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1"), os.environ.get("BENCH_CPUS", "8")
LIMIT = 60.0  # seconds of one query of the experiments; beyond it, a marker stands for the result


def main() -> None:
    spark = (
        SparkSession.builder.master(f"local[{CPUS}]").appName("bench")
        .config("spark.sql.shuffle.partitions", CPUS).config("spark.driver.memory", "8g").config("spark.ui.enabled", "false")
        .config("spark.ui.showConsoleProgress", "false").config("spark.sql.session.timeZone", "UTC").getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    ship(spark)
    sf = float(Path(SF_DIR).name.removeprefix("sf") or 0) if Path(SF_DIR).name.startswith("sf") else None
    seconds: dict[str, float] = {}
    facts: dict[str, object] = {}

    def timed(name: str, action) -> object:
        began = time.perf_counter()
        out = action()
        seconds[name] = round(time.perf_counter() - began, 3)
        return out

    window = 30 if sf and sf >= 0.1 else 300
    graphs = {"basket_r": Graph.from_testdata(spark, SF_DIR, "basket_r"), "coact": Graph.from_testdata(spark, SF_DIR, "coact", window=window)}
    for name, g in graphs.items():  # loading is not part of a query's time
        facts[f"edges_{name}"] = timed(f"load_{name}", lambda g=g: (g.edges.count(), g.adj.count(), g.stats, g.degree_classes)[0])
    for name, g in graphs.items():
        for w in ("clique4", "house5", "near_clique5", "clique5"):
            for variant in ("edge", "vertex") if w in ("house5", "near_clique5") else ("edge",):
                for policy in ("none", "online"):
                    facts[f"{w}_{variant}_{name}"] = timed(f"{w}_{variant}_{policy}_{name}", lambda g=g, w=w, v=variant, p=policy: match(g, CATALOGUE[w], v, p, "count").first()[0])
        patterns = [CATALOGUE[w] for w in WORKLOAD[:5]]
        for variant in ("edge", "vertex"):  # base, nested, online and both together, in generated loops
            for r in metrics.ablation(g, patterns, variant, limit=LIMIT).collect():
                key = f"{r['pattern']}_{variant}_{r['mode']}_{name}"
                seconds[f"kernel_{key}"] = round(r["seconds"], 3)
                facts[key] = {k: r[k] if k != "speedup" and k != "imbalance" else r[k] and round(r[k], 2) for k in ("cnt", "comparisons", "speedup", "imbalance", "over_limit")}
        for r in metrics.compare_engines(g, patterns, "edge", ("online+nested", "compiled", "interpreted", "tail_factor"), LIMIT).collect():
            key = f"{r['pattern']}_{r['engine']}_{name}"
            seconds[f"engine_{key}"] = round(r["seconds"], 3)
            facts[f"engine_{key}"] = {"cnt": r["cnt"], "times_ours": r["speedup"] and round(r["speedup"], 2), "over_limit": r["over_limit"]}
        for r in metrics.list_usage(g, patterns).collect():
            facts[f"lists_{r['pattern']}_{name}"] = {k: r[k] for k in ("considered", "built", "used", "unused")}
        for r in metrics.aux_memory(g, patterns, ("vertex",)).collect():
            facts[f"list_bytes_{r['pattern']}_{name}"] = {"most": r["most_bytes"], "graph": r["graph_bytes"]}
        timed(f"cycle4_listed_{name}", lambda g=g: match(g, CATALOGUE["cycle4"], "edge", "none", "count").first())
        facts[f"cycle4_{name}"] = timed(f"cycle4_tail_factor_{name}", lambda g=g: counting.count_tail_factor(g, CATALOGUE["cycle4"]).first()[0])
    print(json.dumps({"metric": "total_seconds", "value": round(sum(seconds.values()), 3), "unit": "sec", "queries": seconds, "sf": sf, "facts": facts}))


if __name__ == "__main__":
    main()
