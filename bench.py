"""Times the headline queries; prints one JSON line."""

import json
import math
import os
import statistics
import sys
import time

ROOT = os.path.dirname(os.path.abspath(__file__))
sys.path.insert(0, ROOT)
os.environ["PYTHONPATH"] = f"{ROOT}:{os.environ.get('PYTHONPATH', '')}"


def main() -> None:
    from pyspark.sql import SparkSession
    from pyspark.sql import functions as F

    sf, cpus = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1"), os.environ.get("BENCH_CPUS", "8")
    spark = (
        SparkSession.builder.master(f"local[{cpus}]")
        .config("spark.sql.shuffle.partitions", cpus)
        .config("spark.driver.memory", "8g")
        .config("spark.ui.enabled", "false")
        .config("spark.ui.showConsoleProgress", "false")
        .config("spark.sql.session.timeZone", "UTC")
        .getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    from private_distinct.functions.hashing import SketchKey
    from private_distinct.functions.privacy import SketchSpec, threshold
    from private_distinct.operators import baselines, sketches
    from private_distinct.plans import workloads

    bands = {}

    def timed(make, times=3, band=None):
        took = []
        for _ in range(times):
            t = time.perf_counter()
            make().write.format("noop").mode("overwrite").save()
            took.append(time.perf_counter() - t)
        if band:
            bands[band] = [round(min(took), 4), round(max(took), 4)]
        return statistics.median(took)

    items = spark.read.parquet(f"{sf}/lineitem.parquet").select("l_orderkey").cache()
    n, key, out, per_item = items.count(), SketchKey("bench", "native"), {}, {}
    some = items.limit(1024).cache()
    some.count()
    for k in (128, 512, 2048, 4096):
        spec = SketchSpec("hll", k)
        for name, make in (
            ("hll", lambda: sketches.build_state(items, ["l_orderkey"], spec, key)),
            ("private_hll", lambda: sketches.build_state(items, ["l_orderkey"], spec, key, (), threshold(workloads.EPS))),
            ("per_bucket", lambda: baselines.per_bucket_state(some, ["l_orderkey"], k, key)),
        ):
            out[f"{name}_k{k}"] = timed(make, 10, f"{name}_k{k}")
        per_item[k] = [1e6 * out[f"hll_k{k}"] / n, 1e6 * out[f"private_hll_k{k}"] / n, 1e6 * out[f"per_bucket_k{k}"] / 1024]
    job = timed(lambda: baselines.per_bucket_state(some, ["l_orderkey"], 1, key), 10)  # what a job costs without the hashing

    def slope(name, less=0.0):
        """Of log time in log k, by least squares."""
        at = [(math.log(k), math.log(max(out[f"{name}_k{k}"] - less, 1e-4))) for k in per_item]
        mx, my = (sum(c) / len(at) for c in zip(*at, strict=True))
        return round(sum((x - mx) * (y - my) for x, y in at) / sum((x - mx) ** 2 for x, _ in at), 3)

    slopes = {"hll": slope("hll"), "private_hll": slope("private_hll"), "per_bucket": slope("per_bucket"), "per_bucket_less_job": slope("per_bucket", job)}
    registered = workloads.queries()
    for name in ("any_hll", "any_bottomk", "any_linear", "any_fm", "any_adaptive", "convert_hll", "grouped_priority", "region_segment_customers", "words_per_lang", "baseline_exact"):
        out[name] = timed(lambda: registered[name](spark, sf), 1)
    ids = spark.range(1 << 16)
    ratios = {}
    for k in (128, 512):
        top = [s.agg(F.max("val")).first()[0] for s in (baselines.per_bucket_state(ids.limit(1 << 13), ["id"], k, key), sketches.build_state(ids.limit(1 << 13), ["id"], SketchSpec("hll", k), key, (), threshold(workloads.EPS)))]
        ratios[k] = math.log2(top[0]) / math.log2(top[1])
    print(json.dumps({"metric": "headline queries, total", "value": round(sum(out.values()), 3), "unit": "sec", "queries": {k: round(v, 4) for k, v in out.items()}, "sf": sf, "us_per_item_hll_private_perbucket": {k: [round(x, 3) for x in v] for k, v in per_item.items()}, "bands_of_10": bands, "slope_in_k": slopes, "space_ratio": {k: round(v, 3) for k, v in ratios.items()}}))


if __name__ == "__main__":
    main()
