"""Headline queries at $BENCH_SF_DIR on local[$BENCH_CPUS]; prints one JSON line. All indexes, the compared ones too, are
built and loaded before; a time is the mean of three runs. Generated arrays are sums of Gaussians: 2D of 1,048,576 cells
(8 MB) and 65,536, 3D of 64^3, 4D of 22^4."""

import json
import os
import sys
import time
from pathlib import Path

ROOT = Path(__file__).resolve().parent
sys.path.insert(0, str(ROOT))
os.environ["PYTHONPATH"] = f"{ROOT}:{os.environ.get('PYTHONPATH', '')}"

from pyspark.sql import SparkSession  # noqa: E402
from pyspark.sql import functions as F  # noqa: E402

from gridmask.operators import baselines as B  # noqa: E402
from gridmask.operators import query as Q  # noqa: E402
from gridmask.operators.tree import IndexConfig  # noqa: E402
from gridmask.plans import gauss  # noqa: E402
from gridmask.plans.arrays import PART_CELLS, index_of, linear_of, ratio_query  # noqa: E402

HITS = {"005": 0.005, "10": 0.1, "50": 0.5, "100": 1.0}
CFG = IndexConfig(part_cells=PART_CELLS)


def main() -> None:
    sf = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
    cpus = os.environ.get("BENCH_CPUS", "8")
    spark = SparkSession.builder.master(f"local[{cpus}]").config("spark.sql.shuffle.partitions", cpus).config("spark.driver.memory", "8g").config("spark.ui.enabled", "false").config("spark.sql.session.timeZone", "UTC").config("spark.ui.showConsoleProgress", "false").getOrCreate()
    spark.sparkContext.setLogLevel("ERROR")
    out: dict = {}
    space: dict = {}
    runs: dict = {}

    def built(name: str, f):
        t0 = time.time()
        x = f()
        out[f"build_{name}"] = round(time.time() - t0, 3)
        return x

    table = built("2d", lambda: index_of(spark, sf, "a2p"))
    lines = built("2d_rect_clip", lambda: linear_of(spark, sf, "a2p", encoding="interval"))
    columns = built("2d_dim_columns", lambda: linear_of(spark, sf, "a2p", "all"))
    q10 = ratio_query(table, 0.1)
    for tag, hit in HITS.items():
        runs[f"tree_2d_{tag}"] = lambda q=ratio_query(table, hit): Q.range_query(table, q)
    third = index_of(spark, sf, "a3")
    q3 = ratio_query(third, 0.1)
    runs["tree_3d_10"] = lambda: Q.range_query(third, q3)
    runs["tree_count_2d_10"] = lambda: Q.count_query(table, q10)
    runs["rect_clip_2d_10"] = lambda: B.rect_clip(lines, q10)
    runs["dim_columns_2d_10"] = lambda: B.dim_columns(columns, q10)
    runs["zone_map_2d_10"] = lambda: B.zone_map(table, q10)
    runs["zone_map_2d_005"] = lambda q=ratio_query(table, 0.005): B.zone_map(table, q)

    def compared(name: str, shape: tuple[int, ...], hits: dict[str, float], parts=None) -> None:
        """The three methods on a generated array."""
        tree = built(f"gauss_{name}", lambda: gauss.index(spark, shape, parts, CFG))
        one = built(f"gauss_{name}_rect_clip", lambda: gauss.linear(spark, shape, "value", parts, encoding="interval"))
        all_ = built(f"gauss_{name}_dim_columns", lambda: gauss.linear(spark, shape, "all", parts))
        own = Q.index_bytes(tree).agg(F.sum(F.col("bitmap_bytes") + F.col("meta_bytes"))).first()[0]
        space[name] = {"tree": own} | {m: B.bitmap_bytes(i).agg(F.sum("bytes")).first()[0] for m, i in (("rect_clip", one), ("dim_columns", all_))}
        for tag, hit in hits.items():
            q = ratio_query(tree, hit)
            runs[f"gauss_{name}_tree_{tag}"] = lambda q=q: Q.range_query(tree, q)
            runs[f"gauss_{name}_rect_clip_{tag}"] = lambda q=q: B.rect_clip(one, q)
            runs[f"gauss_{name}_dim_columns_{tag}"] = lambda q=q: B.dim_columns(all_, q)

    compared("2d_05mb", (256, 256), {"10": 0.1})
    compared("2d_8mb", (1024, 1024), HITS)
    compared("3d", (64, 64, 64), {"10": 0.1, "50": 0.5}, gauss.random_components(3, 4))
    compared("4d", (22, 22, 22, 22), {"10": 0.1, "50": 0.5}, gauss.random_components(4, 4))
    for name, f in runs.items():
        f().write.format("noop").mode("overwrite").save()  # loaded, code compiled
        took = []
        for _ in range(3):
            t0 = time.time()
            f().write.format("noop").mode("overwrite").save()
            took.append(time.time() - t0)
        out[name] = round(sum(took) / 3, 3)
    total = sum(v for k, v in out.items() if not k.startswith("build_"))
    print(json.dumps({"metric": "sum of mean query seconds", "value": round(total, 3), "unit": "sec", "queries": out, "sf": sf, "index_bytes": space}))


if __name__ == "__main__":
    main()
