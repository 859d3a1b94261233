"""Headline queries at $BENCH_SF_DIR on local[$BENCH_CPUS]; prints one JSON line."""

from __future__ import annotations

import json
import os
import sys
import time

HERE = os.path.dirname(os.path.abspath(__file__))
sys.path.insert(0, HERE)
os.environ["PYTHONPATH"] = f"{HERE}:{os.environ.get('PYTHONPATH', '')}"
os.environ.setdefault("OMP_NUM_THREADS", "1")

from pyspark.sql import SparkSession  # noqa: E402

HEADLINES = [
    "marginals_all_1way", "marginals_all_3way_lines", "marginals_all_3way_sales", "marginals_all_3way_wide", "tabulate_grouping_sets", "tabulate_bincount", "residual_coords", "roundtrip_exact",
    "kron_decompose", "reconstruct_mle", "lazy_update", "adaptive_release", "adaptive_release_cluster", "batch_release", "release_costs", "transform_tiled", "ablation", "tradeoff", "tradeoff_large",
    "transform_bench",
]
#: Queries whose rows go into the facts.
TOLD = ("ablation", "tradeoff", "tradeoff_large", "transform_bench", "release_costs", "transform_tiled")
PUBLISHED = {"full_over_lazy": "7.2-23.2", "iid_over_conditional": "2.0-12.9", "full_iid_over_lazy_conditional": "18.5-92.5", "error_iid_over_conditional": "1.03-1.13", "graphical_over_adaptive_seconds": "up to 697", "adaptive_over_batch_error": "worst 1.15-1.37", "graphical_over_batch_error": "worst up to 14.0", "kron_over_in_axis_decompose_n16": "3.14", "kron_over_in_axis_decompose_degree3": "3.75"}


def mean(rows: list[dict], column: str, **where) -> float:
    own = [r[column] for r in rows if all(r[k] == v for k, v in where.items())]
    return sum(own) / len(own) if own else float("nan")


def facts_of(told: dict[str, list[dict]]) -> dict:
    """Ratios that the reference reports, from the rows of the experiments."""
    out: dict = {"published": PUBLISHED}
    for data in ("sales", "bits", "wide"):
        full, lazy, conditional = ({c: mean(told["ablation"], c, dataset=data, strategy=s) for c in ("seconds", "l1", "updates")} for s in ("full_iid", "lazy_iid", "lazy_conditional"))
        out[f"ablation.{data}"] = {
            "seconds": [round(x["seconds"], 3) for x in (conditional, lazy, full)], "updates": [round(x["updates"]) for x in (conditional, lazy, full)],
            "full_over_lazy": round(full["seconds"] / lazy["seconds"], 2), "iid_over_conditional": round(lazy["seconds"] / conditional["seconds"], 2),
            "full_iid_over_lazy_conditional": round(full["seconds"] / conditional["seconds"], 2), "error_iid_over_conditional": round(lazy["l1"] / conditional["l1"], 3),
        }
    for name in ("tradeoff", "tradeoff_large"):
        rows = told[name]
        for data in sorted({r["dataset"] for r in rows}):
            table = {}
            for eps in sorted({r["eps"] for r in rows if r["dataset"] == data}):
                of = lambda m, c: mean(rows, c, dataset=data, eps=eps, method=m)  # noqa: E731,B023
                table[str(eps)] = {m: [round(of(m, "l1") / of("batch", "l1"), 3), round(of(m, "seconds"), 4)] for m in sorted({r["method"] for r in rows if r["dataset"] == data})}
            out[f"tradeoff.{data}.error_over_batch_and_seconds"] = table
            if any(r["method"] == "graphical" for r in rows if r["dataset"] == data):
                out[f"tradeoff.{data}.graphical_over_adaptive_seconds"] = round(max(mean(rows, "seconds", dataset=data, eps=e, method="graphical") / mean(rows, "seconds", dataset=data, eps=e, method="adaptive") for e in {r["eps"] for r in rows}), 1)
    times = {(r["impl"], r["op"], r["degree"], r["n"]): r["seconds"] for r in told["transform_bench"]}
    ratios = {(op, d, n): times["kron", op, d, n] / t for (impl, op, d, n), t in times.items() if impl == "in_axis"}
    out["kron_over_in_axis"] = {f"{op}.{d}.{n}": round(x, 2) for (op, d, n), x in ratios.items()}
    for op in ("decompose", "reconstruct"):
        for name, keep in (("n16", lambda d, n: n == 16), ("degree3", lambda d, n: d == 3 and n != 16)):
            own = [x for (o, d, n), x in ratios.items() if o == op and keep(d, n)]
            out[f"kron_over_in_axis_{op}_{name}"] = round(sum(own) / len(own), 2)
    out["release_costs.sales"], out["transform_tiled"] = told["release_costs"][0], told["transform_tiled"]
    return out


def main() -> None:
    sf_dir = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
    cpus = os.environ.get("BENCH_CPUS", "8")
    spark = (
        SparkSession.builder.master(f"local[{cpus}]").config("spark.sql.shuffle.partitions", cpus).config("spark.driver.memory", "8g")
        .config("spark.ui.enabled", "false").config("spark.ui.showConsoleProgress", "false").getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    from residual_marginals import catalog, measures

    seconds, details = {}, {}
    measures.force(catalog.QUERIES["marginal_1way_flag"](spark, sf_dir))  # warm-up
    for name in HEADLINES:
        began = time.perf_counter()
        out = catalog.QUERIES[name](spark, sf_dir)
        if name in TOLD:
            details[name] = [r.asDict() for r in out.collect()]
        else:
            measures.force(out)
        seconds[name] = round(time.perf_counter() - began, 3)
    facts = facts_of(details)
    print(json.dumps({"metric": "total_query_seconds", "value": round(sum(seconds.values()), 3), "unit": "sec", "queries": seconds, "sf": os.path.basename(sf_dir), "facts": facts}))
    spark.stop()


if __name__ == "__main__":
    main()
