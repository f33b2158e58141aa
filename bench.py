"""Times the headline queries at $BENCH_SF_DIR on local[$BENCH_CPUS]; prints one JSON line."""

from __future__ import annotations

import json
import os
import time

from pyspark.sql import SparkSession

from proxrec.operators import linalg, model
from proxrec.operators.model import ModelSpec, fit
from proxrec.plans.planner import cut
from proxrec.registry import trials
from proxrec.sources.workloads import VIEWS

SF_DIR = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
CPUS = os.environ.get("BENCH_CPUS", "4")


def timed(found: dict, name: str, run) -> object:
    t = time.perf_counter()
    out = run()
    found[name] = round(time.perf_counter() - t, 3)
    return out


def main() -> None:
    spark = (
        SparkSession.builder.master(f"local[{CPUS}]").appName("bench").config("spark.sql.shuffle.partitions", CPUS).config("spark.driver.memory", "8g")
        .config("spark.ui.enabled", "false").config("spark.sql.session.timeZone", "UTC").getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    times: dict[str, float] = {}
    more: dict[str, object] = {}
    spark.range(1000).selectExpr("sum(id)").collect()
    purchases = timed(times, "ratings_purchases", lambda: cut(VIEWS["purchases"](spark, SF_DIR)))
    terms = timed(times, "ratings_doc_terms", lambda: cut(VIEWS["doc_terms"](spark, SF_DIR)))
    spec = ModelSpec("cosine", 0.4, 50, tol=1e-4, form="local", solver="lanczos", allow_partial=True)
    fitted = timed(times, "fit_purchases_f50", lambda: fit(purchases, spec))
    timed(times, "recommend_all_users", lambda: model.recommend(fitted, purchases, 10).write.format("noop").mode("overwrite").save())
    timed(times, "fit_blocks_f20", lambda: fit(purchases, ModelSpec("cosine", 0.4, 20, tol=1e-3, form="blocks")))
    more["end_to_end_all_users_s"] = round(times["ratings_purchases"] + times["fit_purchases_f50"] + times["recommend_all_users"], 3)
    for view, ratings in (("purchases", purchases), ("doc_terms", terms)):
        users, items, row, column, value = model.triplets(ratings)
        for f in (50, 100):
            op, _ = model.local_operator(row, column, value, len(users), len(items), "cosine", 0.2)
            found = timed(times, f"lanczos_{view}_f{f}", lambda op=op, f=f: linalg.lanczos(op, f, 1e-4, allow_partial=True))
            more[f"{view}_f{f}"] = {"steps": found.trace.steps, "residual": float(f"{max(found.trace.residuals) / found.values[0]:.1e}")} | {k: round(v, 3) for k, v in found.trace.shares().items()}
    more["product_speed_up"] = {str(r["tasks"]): round(r["speed_up"], 2) for r in trials.QUERIES["x8_speed_up"](spark, SF_DIR).collect() if r["tasks"] <= int(CPUS)}
    print(json.dumps({"metric": "headline_total", "value": round(sum(times.values()), 3), "unit": "sec", "queries": times, "sf": SF_DIR.rsplit("sf", 1)[-1], "traces": more}))


if __name__ == "__main__":
    main()
