"""The engine on a small cloud: methods agree, plans are what they should be, defects stay away."""

import glob
import os
import random

import pytest
from pyspark.sql import functions as F

from pointtree import registry
from pointtree.config import TreeConfig
from pointtree.functions import quantize
from pointtree.functions.quantize import Fixed, Frame, Span
from pointtree.operators import baselines, leaves, measures, query, topology
from pointtree.plans import book, experiments
from pointtree.plans.workloads import SINGLE, boxes, part_box
from pointtree.sources import clouds, store

CONFIG = TreeConfig(leaf_limit=20, shard_points=1500)


@pytest.fixture(scope="module")
def air(spark, sf):
    p, f = clouds.gridded(spark, sf, "air")
    return p.cache(), f


@pytest.fixture(scope="module")
def built(air):
    return store.build(*air, CONFIG, ("intensity", "scan_angle", "scan_direction"))


def rows(df):
    return sorted(map(tuple, df.collect()))


def test_three_ways_to_the_same_leaves(air):
    p, f = air
    parts = f.parts(CONFIG)
    got = [rows(topology.leaf_levels(p, CONFIG, parts, m).groupBy("path", "leaf_level").count()) for m in ("window", "iterative", "histogram")]
    assert got[0] == got[1] == got[2] and len(got[0]) > 10


def test_tree_boxes_without_counts_of_all_levels(spark, sf, air, monkeypatch):
    p, f = air
    parts = f.parts(CONFIG)
    want = rows(topology.classify_nodes(topology.level_histogram(p, parts), len(parts), 20).select("level", "path", "cnt", "kind"))
    for shard_points in (20, 300, 1 << 30):
        assert rows(topology.tree_boxes(p, parts, 20, shard_points).select("level", "path", "cnt", "kind")) == want
    monkeypatch.setattr(topology, "level_histogram", None)  # a row for each cell and level: too many for the disk
    assert rows(book.nodes_of(spark, sf, "air", CONFIG)[0].select("level", "path", "cnt", "kind")) == want


def test_boxes_of_all_structures(spark, air, built):
    p, f = air
    table = leaves.build(p, CONFIG, f.parts(CONFIG), ("intensity",)).cache()
    raw = baselines.write_raw(p)
    blocks = baselines.build_block_delta(p, f.parts(CONFIG), ("pid",), ("intensity",), 700)
    sorted_ = baselines.write_sorted(p, f.parts(CONFIG), files=3)
    where = [("intensity", 10, 20)]
    for part in SINGLE.values():
        box = part_box(f, *part)
        want = rows(baselines.brute_box(p, box))
        assert rows(query.points_in_box(built, box)) == want
        assert rows(leaves.points_in_box(table, box)) == want
        assert rows(baselines.raw_scan(spark, raw, box)) == want
        assert rows(baselines.block_box(blocks, box)) == want
        assert rows(baselines.sorted_parquet_box(spark, sorted_, box)) == want
        want = rows(baselines.brute_box(p, box, ["intensity"], where))
        assert rows(query.points_in_box_where(built, box, where, ["intensity"], value_index=True)) == want
        assert rows(leaves.points_in_box(table, box, ("intensity",), where, True)) == want
        assert rows(baselines.block_box(blocks, box, ["intensity"], where)) == want
        assert query.count_in_box(built, box).first()[0] == len(rows(baselines.brute_box(p, box)))


def test_batch_equals_single_queries(spark, air, built):
    p, f = air
    b = boxes(spark, f, 40)
    got = dict(rows(query.counts_in_boxes(built, b)))
    for r in random.Random(1).sample(b.collect(), 4):
        assert got[r["q"]] == baselines.brute_box(p, (r.xi, r.yi, r.zi, r.xe, r.ye, r.ze)).count()


def test_single_box_plan_prunes_and_moves_nothing(built, air):
    _, f = air
    df = query.points_in_box(built, part_box(f, *SINGLE["small"]), ["intensity"])
    plan = df._jdf.queryExecution().toString()
    physical = plan.split("== Physical Plan ==")[1]
    assert "Exchange" not in physical and "PushedFilters: [" in physical and "x_min" in physical
    assert "a_scan_angle" not in physical.split("ReadSchema")[1]


def test_store_opens_again_and_ties_are_fixed(spark, air, built):
    p, f = air
    again = store.open_store(spark, built.path)
    assert (again.parts, again.frame.extent, again.attributes) == (built.parts, f.extent, built.attributes)
    other = store.build(p.repartition(7, "scan_angle"), f, CONFIG, ("intensity", "scan_angle", "scan_direction"))
    cols = ["shard", "t_branch", "t_occupied", "t_tally", "c_x", "a_intensity"]
    assert rows(other.shards().select(*cols)) == rows(built.shards().select(*cols))


def test_one_datum_and_nearest(air, built):
    p, _ = air
    everything = rows(query.scan_all(built, []))
    found = [tuple(query.point_at(built, i).first())[:3] for i in (0, 17, len(everything) - 1)]
    assert all(t in everything for t in found) and query.point_at(built, len(everything)).isEmpty()
    near = query.knn(built, 1000, 1000, 1000, 5).collect()
    want = sorted((r.x - 1000) ** 2 + (r.y - 1000) ** 2 + (r.z - 1000) ** 2 for r in p.collect())[:5]
    assert [r.d2 for r in near] == want


def test_frames(spark):
    df = spark.createDataFrame([(1, -1.5, 2.25, 0.0), (2, 3.5, 2.25, 9.0), (3, None, 1.0, 1.0)], "pid long, rx double, ry double, rz double")
    f = quantize.fit_frame(df, Fixed((10, 100, 1)))
    assert f.low == (-15, 225, 0) and f.extent == (50, 0, 9) and quantize.rejects(df).count() == 1
    assert rows(quantize.restore(quantize.apply(df, f), f).select("rx", "ry", "rz")) == [(-1.5, 2.25, 0.0), (3.5, 2.25, 9.0)]
    s = quantize.fit_frame(df, Span((1000,) * 3, (10, 100, 1)))
    assert s.extent == (1000, 0, 1000) and rows(quantize.apply(df, s).select("x", "y", "z")) == [(0, 0, 0), (1000, 0, 1000)]
    assert quantize.clamp((5, 0, 0, 2, 9, 9), (9, 9, 9)) is None
    flat = Frame(Fixed(), (0, 0, 0), (1 << 20, 1 << 20, 9), 1)
    assert flat.narrow_axes(TreeConfig(), 5) == ["z"]


def test_empty_cloud_and_empty_box(spark):
    p = spark.createDataFrame([], "pid long, x long, y long, z long")
    s = store.build(p, Frame(Fixed(), (0, 0, 0), (7, 7, 7), 0), TreeConfig())
    assert query.scan_all(s).count() == 0 and query.points_in_box(s, None).count() == 0


def test_entry_and_registry(spark, sf):
    df = registry.entry(spark, sf)
    assert df.count() > 0 and df.columns == ["x", "y", "z", "intensity"]
    assert set(registry.oracle_sql()) <= set(registry.queries())


def test_streams_equal_batches(spark, sf):
    from pointtree.streaming import ingest

    e = clouds.table(spark, sf, "events")
    assert ingest.stream_dedup(spark, sf).first()[0] == e.count()
    want = rows(ingest.zoned(e).groupBy("zone").count())
    assert [(r[0], r[1]) for r in rows(ingest.stream_split(spark, sf))] == want
    p, _ = clouds.gridded(spark, sf, "events")
    assert rows(ingest.stream_ingest(spark, sf)) == rows(p.where(F.col("x").between(500_000, 1_500_000)).select("x", "y", "z", "event_code"))


def against_sql(spark, sf, name):
    import duckdb
    con = duckdb.connect()
    for path in glob.glob(f"{sf}/*.parquet"):
        con.execute(f"CREATE VIEW {os.path.basename(path)[:-8]} AS SELECT * FROM '{path}'")
    found = registry.queries()[name](spark, sf)
    want = con.execute(f"SELECT {', '.join(found.columns)} FROM ({registry.oracle_sql()[name]})").fetchall()
    assert rows(found) == sorted(want)
    return want


def test_whole_tables_of_paths_and_maps(spark, sf):
    orders, lines = (spark.read.parquet(f"{sf}/{t}.parquet").count() for t in ("orders", "lineitem"))
    assert len(against_sql(spark, sf, "fn_path")) == orders - 1
    assert len(against_sql(spark, sf, "fn_map")) == lines


def test_every_value_out_of_codes(spark, sf):
    assert len(against_sql(spark, sf, "mlv_access")) == spark.read.parquet(f"{sf}/orders.parquet").count()


def test_early_stop_decodes_less():
    import numpy as np

    from pointtree.operators import shards

    rng = np.random.default_rng(1)
    x, y, z = rng.integers(0, 256, (3, 4000))
    for parts, order, stop in (((2,) * 8, "zorder", "code"), ((4,) * 4, "zorder", "code"), ((2,) * 8, "lex", "x"), ((4, 2, 4, 2, 4), "zorder", "code")):
        t = shards.pack(x, y, z, np.arange(4000), {}, parts, 200, order)
        read, checked = {"none": 0, stop: 0}, {"none": 0, stop: 0}
        for _ in range(20):
            low = rng.integers(0, 200, 3)
            box = (*low.tolist(), *(low + 12).tolist())
            want = sorted((a, b, c) for a, b, c in zip(x, y, z, strict=True) if all(lo <= v <= lo + 12 for lo, v in zip(low, (a, b, c), strict=True)))
            for mode in ("none", stop):
                w = shards.Work()
                got = shards.scan(t, box, stop=mode, work=w)
                assert sorted(zip(got["x"], got["y"], got["z"], strict=True)) == want and shards.count(t, [box])[0] == len(want) == w.points_out
                read[mode] += w.coordinates_read
                checked[mode] += w.points_checked
        assert checked[stop] < 0.8 * checked["none"] and read[stop] < 0.95 * read["none"]


def test_crowded_cells_are_dealt_to_pieces(spark):
    rows_ = [(i, 3, 3, 3, i) for i in range(500)] + [(500 + i, i % 8, i // 8 % 8, 5, i) for i in range(64)]
    p = spark.createDataFrame(rows_, "pid long, x long, y long, z long, v int")
    c = TreeConfig(leaf_limit=4, shard_points=60)
    frame = Frame(Fixed(), (0, 0, 0), (7, 7, 7), len(rows_))
    s = store.build(p, frame, c, ("v",))
    assert s.shards().agg(F.max("cnt")).first()[0] < 110 and s.shards().where("piece > 0").count() > 4
    assert rows(query.scan_all(s)) == sorted(r[1:] for r in rows_)
    assert query.count_in_box(s, (3, 3, 3, 3, 3, 5)).first()[0] == 501
    table = leaves.build(p, c, frame.parts(c), ("v",))
    assert table.agg(F.max("cnt")).first()[0] < 110 and rows(leaves.points_in_box(table, (0, 0, 0, 7, 7, 7), ("v",))) == sorted(r[1:] for r in rows_)


def test_rank_and_select_over_blocks(spark):
    from pointtree.operators import bitvec

    r = random.Random(3)
    on = sorted(r.sample(range(100_000), 700)) + list(range(70_000, 70_050))
    on = sorted(set(on))
    flags = spark.range(100_000).select(F.col("id").alias("i"), F.col("id").isin(on).cast("int").alias("bit"))
    blocks = bitvec.bit_blocks(flags)
    got = rows(bitvec.bit_and_rank(spark.createDataFrame([(i,) for i in (0, 32767, 32768, 65535, 70_020, 99_999, on[0], on[-1], 100_000 + 32768)], "i long"), blocks, "i").where("bit is not null").select("i", "bit", "rank"))
    assert got == sorted((i, int(i in on), sum(j <= i for j in on)) for i in {0, 32767, 32768, 65535, 70_020, 99_999, on[0], on[-1]})
    assert rows(bitvec.select(spark.range(len(on) + 5).withColumnRenamed("id", "j"), blocks)) == list(enumerate(on))


def test_late_rows_are_dropped(spark, sf):
    from pointtree.streaming import ingest

    assert rows(ingest.stream_late(spark, sf)) == rows(ingest.stream_late(spark, sf, late=False))


def test_ingest_goes_on_after_a_restart(spark):
    from pointtree.streaming import ingest

    frame, c = Frame(Fixed(), (0, 0, 0), (63, 63, 63), 100), TreeConfig(leaf_limit=4, shard_points=50)
    part = lambda lo, hi: spark.createDataFrame([(i, i % 64, i * 7 % 64, i * 13 % 64, i) for i in range(lo, hi)], "pid long, x long, y long, z long, v int")
    box = (0, 0, 0, 63, 63, 63)
    want = lambda n: sorted((i % 64, i * 7 % 64, i * 13 % 64, i) for i in range(n))
    one = ingest.Ingest(spark, frame, c, ("v",))
    assert one.points_in_box(box, ("v",)).count() == 0 and query.scan_all(one.compact()).count() == 0
    one.add(part(0, 60), 0)
    one.add(part(60, 90), 1)
    two = ingest.Ingest(spark, frame, c, ("v",), one.path)  # as after a restart
    two.add(part(60, 100), 1)  # the batch comes again
    assert rows(two.points_in_box(box, ("v",))) == want(100)
    two.compact()
    two.add(part(60, 100), 1)
    three = ingest.Ingest(spark, frame, c, ("v",), one.path)
    three.add(part(100, 130), 2)
    assert rows(three.points_in_box(box, ("v",))) == want(130) and len(three.stores) == 2


def agrees(spark, folder, name):
    """The query's rows on a folder of tables are those of its SQL."""
    import duckdb

    con = duckdb.connect()
    for p in glob.glob(f"{folder}/*.parquet"):
        con.execute(f"create view {os.path.basename(p)[:-8]} as select * from read_parquet('{p}{'/*.parquet' if os.path.isdir(p) else ''}')")
    want = con.execute(registry.oracle_sql()[name]).df()
    got = registry.queries()[name](spark, folder).select(*want.columns)
    return sorted(map(str, rows(got))) == sorted(map(str, want.astype(object).itertuples(index=False, name=None)))


def test_repeats_where_every_leaf_is_a_cell(spark, sf, tmp_path):
    t = clouds.table(spark, sf, "lineitem").where("l_quantity in (1, 50) and l_discount in (0, 0.1) and l_tax in (0, 0.08)")
    t.crossJoin(spark.range(200)).drop("id").write.parquet(str(tmp_path / "lineitem.parquet"))
    assert agrees(spark, str(tmp_path), "repeat_census")  # no leaf has coordinates: 0 leaves, not null


def test_whole_tree_is_traced_without_one_shard_of_all_points(spark, sf, monkeypatch):
    built = []
    monkeypatch.setattr(store, "build", lambda *a, **k: built.append(a))
    assert agrees(spark, sf, "box_trace_tree") and not built


@pytest.mark.parametrize("name", ["edge_all_equal", "edge_empty_cloud", "edge_fanout_four", "edge_height_one", "edge_limit_one", "edge_one_point"])
def test_edges_are_clouds_of_customers(spark, sf, tmp_path, name):
    clouds.table(spark, sf, "customer").where("c_custkey < 30").write.parquet(str(tmp_path / "customer.parquet"))
    assert "customer" in registry.oracle_sql()[name] and agrees(spark, str(tmp_path), name)


def test_rejects_are_counted_in_customers(spark, sf, tmp_path):
    clouds.table(spark, sf, "customer").where("c_custkey < 31").write.parquet(str(tmp_path / "customer.parquet"))
    assert registry.queries()["rejects"](spark, str(tmp_path)).first().asDict() == {"rejected": 20, "kept": 11} and agrees(spark, str(tmp_path), "rejects")


@pytest.mark.parametrize("method", ["histogram", "iterative"])
def test_leaf_levels_plan_shards_not_leaves(air, monkeypatch, method):
    p, f = air
    planned, plan = [], topology.plan_boxes
    monkeypatch.setattr(topology, "plan_boxes", lambda points, parts, most, *a, **k: planned.append(most) or plan(points, parts, most, *a, **k))
    topology.leaf_levels(p, CONFIG, f.parts(CONFIG), method)
    assert planned == [CONFIG.shard_points]  # boxes of the leaf limit were rows for each cell and level


def test_growth_fits_one_frame_and_counts_no_level_of_all_cells(spark, sf, monkeypatch):
    fitted, fit = [], book.fit_frame
    monkeypatch.setattr(topology, "level_histogram", None)
    monkeypatch.setattr(book, "_built", {})
    monkeypatch.setattr(book, "fit_frame", lambda *a: fitted.append(a) or fit(*a))
    assert agrees(spark, sf, "growth") and len(fitted) == 1  # four clouds on one grid


def test_bytes_of_blocks_are_those_of_the_blocks(spark, sf):
    names = ("air_s", "air_l")
    points, frames = book.together(spark, sf, names)
    whole, attributes = frames["air_s"], clouds.CLOUDS["air_s"].attributes
    ways = [baselines.Way(clouds.CLOUDS[n].tiles, experiments.strips_of(frames[n], b), b) for n in names for b in (300, 1000)]
    want = []
    for n, w in zip([n for n in names for _ in range(2)], ways, strict=True):
        p, f = clouds.gridded(spark, sf, n)
        assert f == frames[n]
        blocks = baselines.build_block_delta(baselines.strips(p, f.extent, w.strips), f.parts(TreeConfig()), baselines.ACQUIRED, attributes, w.block)
        want.append(measures.block_space(blocks).agg(F.sum("bytes")).first()[0])
    assert baselines.block_bytes(points, whole.extent, attributes, ways) == want
    # bins smaller than blocks, and cells that are left to Spark's sort between them
    assert baselines.block_bytes(points, whole.extent, attributes, ways, 170, 60) == want


def test_space_table_builds_no_blocks(spark, sf, monkeypatch):
    monkeypatch.setattr(baselines, "build_block_delta", None)
    got = {(r.cloud, r.format): r for r in experiments.space_table(spark, sf).collect()}
    assert len(got) == 20 and all(r.bytes > 0 for r in got.values())
