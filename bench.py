"""Headline queries and the experiment matrix at $BENCH_SF_DIR on local[$BENCH_CPUS]; prints one JSON line.

What several headline queries share (the suppressed star, the drifting customers) is timed as queries of its own, before
them.  Blocks are timed on polluted databases with results written; the third one holds stability, decomposition, chase
and reduction, on customers whose twins drift, as exact twins have no conflicts.  By default the smallest and the largest
number of twins and plain and tripled columns are taken once each, after a run on the next smaller tables (if they are
there) that warms up, and one on them that counts for growth; ``--matrix N`` takes all seven databases of the
experiments and averages N runs of each.
"""

from __future__ import annotations

import json
import math
import os
import sys
import time
from pathlib import Path

from pyspark.sql import SparkSession

from truekeys.operators import chase, decompose, pollute, profile, propagate, reduce, stability
from truekeys.plans.model import Database
from truekeys.plans.staging import scratch, staged
from truekeys.queries import QUERIES
from truekeys.queries.block3 import drifted
from truekeys.queries.registry import NKS, ORDER, polluted, suppressed

FOLDER = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1").rstrip("/")
CPUS = os.environ.get("BENCH_CPUS", "4")
SMALLER = str(Path(FOLDER).with_name("sf0.01"))
HEADLINES = [
    "rrp_database", "rrp_lineitem", "sk_candidates_all", "g3_documents_source", "au_documents_text", "au_lineitem_false_nk", "sk_map_documents", "sk_map_part",
    "suppress_star_lineitem", "au_report_star", "theorem_no_au_star", "stability_documents", "stability_part_pname", "stability_customer_drift", "split_history_customer",
    "chase_rule_majority", "chase_mixed_types", "reduced_lineitem", "roundtrip_df30", "analytics_clean", "baseline_distinct_star", "baseline_local_dedup_sizes", "inds_star", "join_asof_history", "stream_session_events",
]
SHARED = {"shared: suppressed star": suppressed, "shared: drifting customers": drifted}
MATRIX = [(d, 1) for d in (0.1, 0.2, 0.3, 0.4, 0.5)] + [(0.3, 2), (0.3, 3)]
SHORT = [(0.1, 1), (0.5, 1), (0.3, 1), (0.3, 3)]
BLOCKS = ("profiles", "suppression", "normalise and reduce")


def timed(f) -> float:  # noqa: ANN001
    start = time.perf_counter()
    f()
    return time.perf_counter() - start


def run_all(df) -> None:  # noqa: ANN001
    df.write.format("noop").mode("overwrite").save()


def blocks(spark: SparkSession, folder: str, df: float, times: int, edges: dict | None = None) -> dict[str, float]:
    """Seconds of the three blocks on one polluted database, whose making is not timed; edges takes figures by foreign key."""
    with scratch(spark):
        made = polluted(spark, folder, df, times=times)
        made.tables["customer"] = pollute.drift(made.tables["customer"], "c_custkey")
        db = Database(made.spec, {n: staged(t) for n, t in made.tables.items()})
        out = {"rows": sum(t.count() for t in db.tables.values())}
        out["profiles"] = timed(lambda: run_all(profile.rrp_database(db)))
        state: dict = {}

        def suppress() -> None:
            state["done"] = propagate.suppress(db, lineage=True)
            state["db"] = Database(db.spec, {n: staged(t) for n, t in state["done"].db.tables.items()})

        def normalise() -> None:
            clean = state["db"]
            for n in ORDER:
                t, key = clean.tables[n], list(NKS[n])
                rest = list(db.spec.relations[n].remaining())
                roles = stability.classify(stability.profile(t, key, rest)).collect() if rest else []  # one row an attribute
                unstable = [r["attribute"] for r in roles if r["role"] == "AtbN"]
                past = [a for a in unstable if a.startswith("c_acctbal")]
                if past:
                    run_all(decompose.history(decompose.completed(clean, n, "orders.o_orderdate"), ["new_id"], key, ["o_orderdate"], past))
                    t = t.drop(*past)
                conflicting = [a for a in unstable if a not in past]
                if conflicting:
                    t = chase.resolve(t, key, conflicting, propagate.LINEAGE + "new_id")
                run_all(reduce.relation(t))

        out["suppression"] = timed(suppress)
        out["normalise and reduce"] = timed(normalise)
        if edges is not None:
            for f in db.spec.sfks():
                m = state["done"].maps[f.target, f.target_columns[0]]
                joined = propagate.apply_map(db.tables[f.source], f.columns[0], m)
                run_all(joined)
                kind = joined._jdf.queryExecution().executedPlan().toString()
                edges[f"{f.source}.{f.columns[0]}"] = {"map_rows": m.count(), "join": next((k for k in ("BroadcastHashJoin", "SortMergeJoin", "ShuffledHashJoin") if k in kind), "other")}
    return out


def main() -> None:
    conf = {"spark.sql.shuffle.partitions": str(2 * int(CPUS)), "spark.ui.enabled": "false", "spark.driver.memory": os.environ.get("BENCH_MEMORY", "6g"), "spark.sql.session.timeZone": "UTC", "spark.ui.showConsoleProgress": "false"}
    spark = SparkSession.builder.master(f"local[{CPUS}]").config(map=conf).getOrCreate()
    spark.sparkContext.setLogLevel("ERROR")
    run_all(QUERIES["rrp_nation"](spark, FOLDER))  # start-up
    queries = {n: round(timed(lambda f=f: f(spark, FOLDER)), 3) for n, f in SHARED.items()}
    queries |= {n: round(timed(lambda n=n: run_all(QUERIES[n](spark, FOLDER))), 3) for n in HEADLINES}
    repeats = int(sys.argv[sys.argv.index("--matrix") + 1]) if "--matrix" in sys.argv else 1
    matrix, growth, edges = {}, {}, {}
    if os.path.isdir(SMALLER) and SMALLER != FOLDER:
        blocks(spark, SMALLER, 0.3, 1)  # warm-up
        matrix["smaller, df30x1"] = {k: round(v, 3) for k, v in blocks(spark, SMALLER, 0.3, 1).items()}
    for d, times in MATRIX if "--matrix" in sys.argv else SHORT:
        runs = [blocks(spark, FOLDER, d, times, edges if (d, times) == (0.3, 1) else None) for _ in range(repeats)]
        matrix[f"df{round(d * 100)}x{times}"] = {k: round(sum(r[k] for r in runs) / repeats, 3) for k in runs[0]}

    def slope(a: str, b: str, k: str) -> float:
        return round(math.log(matrix[b][k] / matrix[a][k]) / math.log(matrix[b]["rows"] / matrix[a]["rows"]), 2)

    for k in BLOCKS:
        if "smaller, df30x1" in matrix:
            growth[k + ", smaller to this"] = slope("smaller, df30x1", "df30x1", k)
        growth[k + ", df10 to df50"] = slope("df10x1", "df50x1", k)
        growth[k + " x3/x1"] = round(matrix["df30x3"][k] / matrix["df30x1"][k], 2)
    print(json.dumps({"metric": "headline queries, total", "value": round(sum(queries.values()), 3), "unit": "sec", "queries": queries, "blocks": matrix, "growth": growth, "edges": edges, "sf": FOLDER.split("/")[-1].removeprefix("sf"), "cpus": int(CPUS)}))


if __name__ == "__main__":
    main()
