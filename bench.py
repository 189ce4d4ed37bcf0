"""Headline queries at $BENCH_SF_DIR on local[$BENCH_CPUS]; prints one JSON line."""

import json
import os
import sys
import time
from statistics import median

sys.path.insert(0, os.path.dirname(os.path.abspath(__file__)))

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from pointtree.config import TreeConfig
from pointtree.operators import baselines, leaves, measures, query
from pointtree.plans.workloads import SINGLE, boxes, part_box
from pointtree.sources import clouds, store

SF_DIR = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
CPUS = os.environ.get("BENCH_CPUS", "4")
REPEAT = 3
WHERE = [("intensity", 10, 20)]
#: All formats hold the same attributes.
HELD = tuple(clouds.RECORD0)
BLOCK = 5_000


def timed(run, repeat: int = REPEAT) -> float:
    taken = []
    for _ in range(repeat):
        began = time.perf_counter()
        out = run()
        if isinstance(out, DataFrame):
            out.write.format("noop").mode("overwrite").save()
        taken.append(time.perf_counter() - began)
    return round(median(taken), 3)


def main() -> None:
    spark = SparkSession.builder.master(f"local[{CPUS}]").appName("bench").config("spark.sql.shuffle.partitions", CPUS).config("spark.driver.memory", "8g").config("spark.ui.enabled", "false").config("spark.ui.showConsoleProgress", "false").getOrCreate()
    spark.sparkContext.setLogLevel("ERROR")
    config = TreeConfig(shard_points=50_000)
    q: dict[str, float] = {}
    kept: dict[str, object] = {}

    def keep(name: str, make):
        kept[name] = make()

    def blocks(p, f, block: int = BLOCK):
        wide = max(1, round((f.count / block) ** 0.5))
        return baselines.build_block_delta(baselines.strips(p, f.extent, wide), f.parts(config), baselines.ACQUIRED, HELD, block)

    frames = {}
    for name in ("air", "cube"):
        p, f = clouds.gridded(spark, SF_DIR, name)
        frames[name] = (p, f)
        q[f"build_store_{name}"] = timed(lambda p=p, f=f, name=name: keep(f"octree_{name}", lambda: store.build(p, f, config, HELD)), 1)
        q[f"build_blocks_{name}"] = timed(lambda p=p, f=f, name=name: keep(f"block_{name}", lambda: blocks(p, f)), 1)
        q[f"build_sorted_{name}"] = timed(lambda p=p, f=f, name=name: keep(f"sorted_{name}", lambda: baselines.write_sorted(p, f.parts(config))), 1)
        q[f"build_raw_{name}"] = timed(lambda p=p, name=name: keep(f"raw_{name}", lambda: baselines.write_raw(p)), 1)
    work, local, failed = {}, {}, {}
    for name in ("air", "cube"):
        f, s, b = frames[name][1], kept[f"octree_{name}"], kept[f"block_{name}"]
        for part in ("third", "slab", "small"):
            box = part_box(f, *SINGLE[part])
            q[f"octree_{part}_{name}"] = timed(lambda s=s, box=box: query.points_in_box(s, box))
            q[f"block_{part}_{name}"] = timed(lambda b=b, box=box: baselines.block_box(b, box))
            q[f"sorted_{part}_{name}"] = timed(lambda name=name, box=box: baselines.sorted_parquet_box(spark, kept[f"sorted_{name}"], box))
            stopped = query.explain_work(s, box, stop="auto").first()
            work[f"{part}_{name}"] = {"octree_checked": query.explain_work(s, box).first()["points_checked"], "octree_checked_with_stop": stopped["points_checked"], "octree_coordinates_read": stopped["coordinates_read"], "block_decoded": baselines.block_work(b, box).first()["points_decoded"]}
        q[f"octree_attr_third_{name}"] = timed(lambda s=s, f=f: query.points_in_box_where(s, part_box(f, *SINGLE["third"]), WHERE))
        q[f"block_attr_third_{name}"] = timed(lambda b=b, f=f: baselines.block_box(b, part_box(f, *SINGLE["third"]), [], WHERE))
        asked = boxes(spark, f).cache()
        ways = {
            "octree": lambda w, s=s, asked=asked: query.counts_in_boxes(s, asked, w),
            "block": lambda w, b=b, asked=asked: baselines.counts_in_blocks(b, asked, w),
            "raw": lambda w, name=name, asked=asked: baselines.counts_in_points(baselines.read_raw(spark, kept[f"raw_{name}"]), asked, w),
            "sorted": lambda w, name=name, asked=asked: baselines.counts_in_points(spark.read.parquet(kept[f"sorted_{name}"]), asked, w),
        }
        want = ways["sorted"]([]).cache()
        for form, run in ways.items():
            q[f"{form}_box500_{name}"] = timed(lambda run=run: run([]), 1)
            q[f"{form}_attr500_{name}"] = timed(lambda run=run: run(WHERE), 1)
            failed[f"{form}_{name}"] = measures.failures(run([]), want).first()["queries_failed"]
        some = [tuple(r)[2:] for r in asked.orderBy("q").limit(100).collect()]  # ten of each size
        for kind, where in (("box", ()), ("attr", WHERE)):
            local[f"{kind}_{name}"] = measures.in_one_process(s, b, kept[f"raw_{name}"], some, where)
    q["raw_third_air"] = timed(lambda: baselines.raw_scan(spark, kept["raw_air"], part_box(frames["air"][1], *SINGLE["third"])))
    p, f = frames["air"]
    q["leaf_table_air"] = timed(lambda: leaves.build(p, config, f.parts(config), ("intensity",)), 1)
    n = f.count
    bits = lambda size: round(8 * size / n, 1)
    total = lambda df: df.agg(F.sum("bytes")).first()[0]
    space = {}
    for name in ("air", "cube"):
        wide = blocks(*frames[name], 50_000)
        sizes = {"raw": 20 * n, "octree": total(measures.space(kept[f"octree_{name}"])), "block_5k": total(measures.block_space(kept[f"block_{name}"])), "block_50k": total(measures.block_space(wide))}
        space[name] = {f"{k}_bits_per_point": bits(v) for k, v in sizes.items()} | {"octree_saves_of_raw": round(measures.saving(sizes["octree"], sizes["raw"]), 1), "block_saves_of_octree": round(measures.saving(sizes["block_50k"], sizes["octree"]), 1)}
    sweep, growth = {}, {}
    for k in (2, 4):
        for limit in (10, 100, 1000):
            c = TreeConfig(fanout=k, leaf_limit=limit, shard_points=50_000)
            began = time.perf_counter()
            s = store.build(p, f, c, ("intensity",))
            sweep[f"k{k}_l{limit}"] = {"build_s": round(time.perf_counter() - began, 2), "bits_per_point": bits(total(measures.space(s)))}
    for name in ("air_s", "air_m", "air_l"):
        part, frame = clouds.gridded(spark, SF_DIR, name)
        began = time.perf_counter()
        s = store.build(part, frame, config, HELD)
        built = time.perf_counter() - began
        began = time.perf_counter()
        query.counts_in_boxes(s, boxes(spark, frame)).write.format("noop").mode("overwrite").save()
        growth[name] = {"points": frame.count, "build_s": round(built, 2), "box500_s": round(time.perf_counter() - began, 2), "bits_per_point": round(8 * total(measures.space(s)) / max(1, frame.count), 1)}
    mean_ms = {k.replace("500", ""): round(2 * v, 2) for k, v in q.items() if "500_" in k}
    faster = {f"{form}_{kind}_{name}": round(measures.speedup(q[f"{form}_{kind}500_{name}"], q[f"octree_{kind}500_{name}"]), 2) for form in ("block", "raw", "sorted") for kind in ("box", "attr") for name in ("air", "cube")}
    more = {"work": work, "space": space, "batch_mean_ms": mean_ms, "batch_speedup_of_octree": faster, "failed_of_500": failed, "one_process": local, "sweep": sweep, "growth": growth}
    print(json.dumps({"metric": "total of headline queries", "value": round(sum(q.values()), 3), "unit": "sec", "queries": q, "sf": os.path.basename(SF_DIR.rstrip("/")).removeprefix("sf"), "points": n, **more}))
    spark.stop()


if __name__ == "__main__":
    main()
