"""What the octree is measured against: raw records, delta-coded blocks under a quadtree, sorted Parquet, brute force."""

from __future__ import annotations

import uuid
import zlib
from collections.abc import Callable, Iterator, Sequence
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.mlv import unzigzag, zigzag
from ..functions.paths import path_of
from ..functions.quantize import Box
from ..sources.shared import shared_dir
from .leaves import within
from .topology import ordered_index, plan_boxes

#: A raw record: 20 bytes.
RECORD = np.dtype([("x", "<i4"), ("y", "<i4"), ("z", "<i4"), ("intensity", "<u2"), ("flags", "u1"), ("classification", "u1"), ("scan_angle", "i1"), ("user_data", "u1"), ("point_source", "<u2")])
RAW_FIELDS = ("intensity", "return_number", "number_of_returns", "scan_direction", "edge_of_flight_line", "classification", "scan_angle", "user_data", "point_source")


def brute_box(points: DataFrame, box: Box, columns: Sequence[str] = (), where: Sequence[tuple[str, int, int]] = ()) -> DataFrame:
    """The plain predicate."""
    p = points.where(within(box))
    for a, lo, hi in where:
        p = p.where(F.col(a).between(lo, hi))
    return p.select("x", "y", "z", *columns)


def write_raw(points: DataFrame, path: str | None = None) -> str:
    """Points with record-0 attributes as uncompressed runs of 20-byte records."""
    path = path or f"{shared_dir(points.sparkSession)}/raw-{uuid.uuid4().hex}"

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            c = {n: b.column(n).to_numpy() for n in ("x", "y", "z", *RAW_FIELDS)}
            r = np.zeros(b.num_rows, RECORD)
            for n in RECORD.names:
                if n != "flags":
                    r[n] = c[n]
            r["flags"] = c["return_number"] | c["number_of_returns"] << 3 | c["scan_direction"] << 6 | c["edge_of_flight_line"] << 7
            yield pa.RecordBatch.from_arrays([pa.array([r.tobytes()], pa.binary())], names=["records"])

    points.select("x", "y", "z", *RAW_FIELDS).mapInArrow(run, "records binary").write.option("compression", "none").parquet(path)
    return path


def read_raw(spark: SparkSession, path: str) -> DataFrame:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for raw in b.column(0):
                r = np.frombuffer(raw.as_py(), RECORD)
                f = r["flags"]
                c = {n: r[n].astype(np.int32) for n in RECORD.names if n != "flags"} | {"return_number": (f & 7).astype(np.int32), "number_of_returns": (f >> 3 & 7).astype(np.int32), "scan_direction": (f >> 6 & 1).astype(np.int32), "edge_of_flight_line": (f >> 7).astype(np.int32)}
                yield pa.RecordBatch.from_arrays([pa.array(c[n].astype(np.int64)) for n in "xyz"] + [pa.array(c[n]) for n in RAW_FIELDS], names=[*"xyz", *RAW_FIELDS])

    return spark.read.parquet(path).mapInArrow(run, "x long, y long, z long, " + ", ".join(f"{n} int" for n in RAW_FIELDS))


def raw_scan(spark: SparkSession, path: str, box: Box, columns: Sequence[str] = (), where: Sequence[tuple[str, int, int]] = ()) -> DataFrame:
    """Every record is read and tested."""
    return brute_box(read_raw(spark, path), box, columns, where)


def _deltas(v: np.ndarray) -> bytes:
    return zlib.compress(zigzag(np.diff(v.astype(np.int64), prepend=0)).astype("<u8").tobytes(), 6)


def _sums(raw: bytes) -> np.ndarray:
    return np.cumsum(unzigzag(np.frombuffer(zlib.decompress(raw), "<u8")))


@dataclass(frozen=True)
class Blocks:
    spark: SparkSession
    path: str
    attributes: tuple[str, ...]

    def blocks(self) -> DataFrame:
        return self.spark.read.parquet(f"{self.path}/blocks")

    def cells(self) -> DataFrame:
        return self.spark.read.parquet(f"{self.path}/cells")


def block_numbers(points: DataFrame, order: Sequence[str], block_points: int) -> DataFrame:
    """Points with the block that their place in acquisition order falls in."""
    return ordered_index(points, *order).withColumn("block", F.call_function("div", F.col("pos"), F.lit(block_points)))


def build_block_delta(points: DataFrame, parts: tuple[int, ...], order: Sequence[str], attributes: tuple[str, ...] = (), block_points: int = 50_000, cell_points: int | None = None, path: str | None = None) -> Blocks:
    """Blocks of points in acquisition order, per-column deltas deflated, and a quadtree over x and y: cell -> blocks."""
    spark = points.sparkSession
    path = path or f"{shared_dir(spark)}/blocks-{uuid.uuid4().hex}"
    names = ("x", "y", "z", *attributes)
    numbered = block_numbers(points, order, block_points)

    def pack(key: tuple, t: pa.Table) -> pa.Table:
        t = t.sort_by("pos")
        row = {"block": key[0].as_py(), "cnt": t.num_rows} | {f"d_{n}": _deltas(t.column(n).to_numpy()) for n in names}
        return pa.Table.from_pydict({k: pa.array([v], pa.int64() if isinstance(v, int) else pa.binary()) for k, v in row.items()})

    numbered.select("block", "pos", *names).groupBy("block").applyInArrow(pack, "block long, cnt long, " + ", ".join(f"d_{n} binary" for n in names)).write.option("compression", "none").parquet(f"{path}/blocks")
    quad_cells(numbered, parts, cell_points or block_points // 4).write.parquet(f"{path}/cells")
    return Blocks(spark, path, attributes)


def quad_cells(numbered: DataFrame, parts: tuple[int, ...], most: int) -> DataFrame:
    """Cells of a quadtree over x and y of up to ``most`` points, with their bounds and blocks."""
    flat = numbered.select("x", "y", F.lit(0).cast("long").alias("z"), "block").withColumn("path", path_of(parts))
    by = plan_boxes(flat, parts, most).beside(flat, "cell").groupBy("cell", "cell_level")
    return by.agg(F.min("x").alias("x_min"), F.max("x").alias("x_max"), F.min("y").alias("y_min"), F.max("y").alias("y_max"), F.collect_set("block").alias("blocks"))


def strips(points: DataFrame, extent: Sequence[int], count: int) -> DataFrame:
    """Points with ``strip``, the flight strip over x that they lie in: acquisition goes strip by strip along y."""
    return points.withColumn("strip", F.call_function("div", F.col("x") * count, F.lit(extent[0] + 1)))


#: Acquisition order of points with strips; blocks of this order are compact in space.
ACQUIRED = ("strip", "y", "x", "pid")
#: Cells that a strip is counted in along y, points of a bin of cells, and of a cell above which Spark sorts its points.
CELLS, BIN_POINTS, HEAVY_POINTS = 64, 250_000, 1_000_000
#: Points that a task deals to bins at a time.
CHUNK_POINTS = 200_000
PIECES = "way int, block long, at long, cnt long, bytes long, data binary"


@dataclass(frozen=True)
class Way:
    """Blocks of ``block`` points in acquisition order over ``strips``, of the points of tiles below ``tiles`` (None: of all)."""

    tiles: int | None
    strips: int
    block: int


def _narrow(v: np.ndarray) -> np.ndarray:
    """The same integers in as few bytes as hold them."""
    low, high = v.min(initial=0), v.max(initial=0)
    return v.astype(next(t for t in (np.int8, np.int16, np.int32, np.int64) if np.iinfo(t).min <= low and high <= np.iinfo(t).max))


def _joined(columns: Sequence[np.ndarray]) -> bytes:
    return b"".join([c.dtype.char.encode() for c in columns] + [c.tobytes() for c in columns])


def _opened(raws: Sequence[bytes], columns: int) -> list[np.ndarray]:
    """Columns of several ``_joined`` runs of points, one after another."""
    parts: list[list[np.ndarray]] = [[] for _ in range(columns)]
    for raw in raws:
        types = [np.dtype(chr(t)) for t in raw[:columns]]
        n, at = (len(raw) - columns) // sum(t.itemsize for t in types), columns
        for held, t in zip(parts, types, strict=True):
            held.append(np.frombuffer(raw, t, n, at))
            at += n * t.itemsize
    return [np.concatenate(held).astype(np.int64) for held in parts]


def _pieces(rows: Sequence[tuple]) -> pa.Table:
    kinds = (pa.int32(), *[pa.int64()] * 4, pa.binary())
    return pa.table([pa.array([r[i] for r in rows], t) for i, t in enumerate(kinds)], names=[c.split()[0] for c in PIECES.split(", ")])


def _size(columns: Sequence[np.ndarray]) -> int:
    return sum(len(_deltas(c)) for c in columns)


def block_bytes(points: DataFrame, extent: Sequence[int], attributes: Sequence[str], ways: Sequence[Way], bin_points: int = BIN_POINTS, heavy_points: int = HEAVY_POINTS) -> list[int]:
    """Bytes of all blocks that ``build_block_delta`` would write of ``points(pid, x, y, z, tile, attributes)``, for each way.

    Counts of cells along the strips give every bin of neighbouring cells its first place, so that points go to bins in
    one exchange for all ways, columns packed, and a bin sorts and encodes its own. A block at the border of bins is
    put together from its pieces. Points of a cell too heavy for one task get their places by Spark's sort.
    """
    spark, names = points.sparkSession, ("pid", "x", "y", "z", *attributes)
    mine = [F.lit(True) if w.tiles is None else F.col("tile") < w.tiles for w in ways]

    def placed(w: Way, columns: dict[str, np.ndarray]) -> tuple[np.ndarray, np.ndarray]:
        """Which points are the way's, and their cells."""
        at = np.arange(len(columns["x"])) if w.tiles is None else np.flatnonzero(columns["tile"] < w.tiles)
        return at, columns["x"][at] * w.strips // (extent[0] + 1) * CELLS + columns["y"][at] * CELLS // (extent[1] + 1)

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        sums = [np.zeros(w.strips * CELLS, np.int64) for w in ways]
        for b in batches:
            columns = {c: b.column(c).to_numpy() for c in ("x", "y", "tile")}
            for n, w in zip(sums, ways, strict=True):
                n += np.bincount(placed(w, columns)[1], minlength=len(n))
        for i, n in enumerate(sums):
            at = np.flatnonzero(n)
            yield pa.RecordBatch.from_arrays([pa.array(np.full(len(at), i, np.int32)), pa.array(at), pa.array(n[at])], names=["way", "cell", "n"])

    counted = points.select("x", "y", "tile").mapInArrow(count, "way int, cell long, n long").groupBy("way", "cell").agg(F.sum("n").alias("n")).collect()  # strips x cells
    bin_of, first_of, way_of, heavy_of, totals = [], [], [], [], []
    for i, w in enumerate(ways):
        n = np.zeros(w.strips * CELLS, np.int64)
        for r in counted:
            if r["way"] == i:
                n[r["cell"]] = r["n"]
        start, heavy = np.cumsum(n) - n, n > heavy_points
        new = np.ones(len(n), bool)  # a bin ends where it is full, and before and after a heavy cell
        new[1:] = (np.diff(start // bin_points) > 0) | heavy[1:] | heavy[:-1]
        bins = np.cumsum(new) - 1 + len(first_of)
        first_of += start[new].tolist()
        way_of += [i] * int(new.sum())
        bin_of.append(np.where(heavy, -1, bins))
        heavy_of.append((np.flatnonzero(heavy), start[heavy] - (np.cumsum(n[heavy]) - n[heavy])))
        totals.append(int(n.sum()))
    shared = spark.sparkContext.broadcast((bin_of, first_of, way_of))

    def deal(columns: dict[str, np.ndarray]) -> Iterator[pa.RecordBatch]:
        narrow = [_narrow(columns[c]) for c in names]
        for w, bins in zip(ways, shared.value[0], strict=True):
            at, cell = placed(w, columns)
            b = bins[cell]
            at, b = at[b >= 0], b[b >= 0]
            by = np.argsort(b, kind="stable")
            own, first = np.unique(b[by], return_index=True)
            held = [c[at[by]] for c in narrow]
            ends = [*first[1:].tolist(), len(b)]
            data = [_joined([c[s:e] for c in held]) for s, e in zip(first.tolist(), ends)]  # noqa: B905
            yield pa.RecordBatch.from_arrays([pa.array(own.astype(np.int32)), pa.array(data, pa.binary())], names=["bin", "data"])

    def to_bins(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[pa.RecordBatch] = []
        for b in batches:
            held.append(b)
            if sum(h.num_rows for h in held) >= CHUNK_POINTS:
                yield from deal(_columns(held))
                held = []
        if held:
            yield from deal(_columns(held))

    def _columns(batches: list[pa.RecordBatch]) -> dict[str, np.ndarray]:
        return {c: np.concatenate([b.column(c).to_numpy(zero_copy_only=False).astype(np.int64) for b in batches]) for c in (*names, "tile")}

    def encode(key: tuple, t: pa.Table) -> pa.Table:
        b = key[0].as_py()
        start, i = shared.value[1][b], shared.value[2][b]
        w, (pid, *columns) = ways[i], _opened(t.column("data").to_pylist(), len(names))
        x, y = columns[:2]
        by = np.lexsort([pid, x, y, x * w.strips // (extent[0] + 1)])
        columns = [c[by] for c in columns]
        end, rows, at = start + len(by), [], start
        while at < end:
            to = min(end, (at // w.block + 1) * w.block)
            run = [c[at - start : to - start] for c in columns]
            whole = to - at == w.block
            rows.append((i, at // w.block, at, to - at, _size(run) if whole else None, None if whole else _joined([_narrow(c) for c in run])))
            at = to
        return _pieces(rows)

    def gather(i: int) -> Callable[[tuple, pa.Table], pa.Table]:
        def run(key: tuple, t: pa.Table) -> pa.Table:
            t = t.sort_by("pos")
            pos, columns = t.column("pos").to_numpy(), [t.column(c).to_numpy().astype(np.int64) for c in names[1:]]
            edges = [0, *(np.flatnonzero(np.diff(pos) > 1) + 1).tolist(), len(pos)]
            return _pieces([(i, key[0].as_py(), int(pos[s]), e - s, None, _joined([_narrow(c[s:e]) for c in columns])) for s, e in zip(edges, edges[1:])])  # noqa: B905

        return run

    rows = points.select(*names, "tile").mapInArrow(to_bins, "bin int, data binary").groupBy("bin").applyInArrow(encode, PIECES)
    for i, (w, (cells, shift)) in enumerate(zip(ways, heavy_of, strict=True)):
        if len(cells):
            places = spark.createDataFrame(list(zip(cells.tolist(), shift.tolist(), strict=True)), "cell long, shift long")
            cell = F.col("strip") * CELLS + F.call_function("div", F.col("y") * CELLS, F.lit(extent[1] + 1))
            heavy = strips(points.where(mine[i]), extent, w.strips).withColumn("cell", cell).join(F.broadcast(places), "cell")
            numbered = ordered_index(heavy, *ACQUIRED).withColumn("pos", F.col("pos") + F.col("shift")).withColumn("block", F.call_function("div", F.col("pos"), F.lit(w.block)))

            rows = rows.unionByName(numbered.select("block", "pos", *names[1:]).groupBy("block").applyInArrow(gather(i), PIECES))

    def finish(key: tuple, t: pa.Table) -> pa.Table:
        t = t.sort_by("at")
        size = t.column("bytes")[0].as_py()
        if size is None:
            size = _size(_opened(t.column("data").to_pylist(), len(names) - 1))
        return pa.table({"way": pa.array([key[0].as_py()], pa.int32()), "cnt": pa.array([sum(t.column("cnt").to_pylist())], pa.int64()), "bytes": pa.array([size], pa.int64())})

    sums = {r["way"]: (r["cnt"], r["bytes"]) for r in rows.groupBy("way", "block").applyInArrow(finish, "way int, cnt long, bytes long").groupBy("way").agg(F.sum("cnt").alias("cnt"), F.sum("bytes").alias("bytes")).collect()}
    got = [sums.get(i, (0, 0)) for i in range(len(ways))]
    if [n for n, _ in got] != totals:
        raise RuntimeError(f"blocks hold {[n for n, _ in got]} points of {totals}: the table has changed meanwhile")
    return [size for _, size in got]


#: Boxes of a batch at most: they are sent to all tasks.
MOST_BOXES = 10_000


def _asked(boxes: DataFrame) -> np.ndarray:
    rows = [tuple(r) for r in boxes.select("q", "xi", "yi", "zi", "xe", "ye", "ze").limit(MOST_BOXES + 1).collect()]
    if len(rows) > MOST_BOXES:
        raise ValueError(f"more than {MOST_BOXES} boxes: join them with the leaf table (surround.join_boxes)")
    return np.array(rows, np.int64).reshape(-1, 7)


def count_each(asked: np.ndarray, columns: dict[str, np.ndarray], where: Sequence[tuple[str, int, int]] = ()) -> tuple[np.ndarray, np.ndarray]:
    """``q`` and the points of each box among the given ones."""
    on = np.ones(len(columns["x"]), bool)
    for a, lo, hi in where:
        on &= (columns[a] >= lo) & (columns[a] <= hi)
    p = np.stack([columns[a][on] for a in "xyz"], 1)
    if not len(p):
        return asked[:0, 0], asked[:0, 0]
    mine = asked[((asked[:, 1:4] <= p.max(0)) & (asked[:, 4:7] >= p.min(0))).all(1)]
    n = [int(((p >= b[1:4]) & (p <= b[4:7])).all(1).sum()) for b in mine]
    return mine[:, 0], np.array(n, np.int64)


def _totals(boxes: DataFrame, found: DataFrame) -> DataFrame:
    n = found.groupBy("q").agg(F.sum("n").alias("n"))
    return boxes.select("q").join(n, "q", "left").select("q", F.coalesce("n", F.lit(0).cast("long")).alias("n"))


def counts_in_points(points: DataFrame, boxes: DataFrame, where: Sequence[tuple[str, int, int]] = ()) -> DataFrame:
    """``q, n`` for every box over plain points (raw records, sorted Parquet): every point is tested once, in batches."""
    shared = points.sparkSession.sparkContext.broadcast(_asked(boxes))
    names = [*"xyz", *dict.fromkeys(w[0] for w in where)]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            q, n = count_each(shared.value, {c: b.column(c).to_numpy() for c in names}, where)
            yield pa.RecordBatch.from_arrays([pa.array(q), pa.array(n)], names=["q", "n"])

    return _totals(boxes, points.select(*names).mapInArrow(run, "q long, n long"))


def met_blocks(b: Blocks, asked: np.ndarray) -> DataFrame:
    """``block, qs``: the boxes that lead to each block by cells that they meet in x and y."""
    shared = b.spark.sparkContext.broadcast(asked)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for c in batches:
            low, high = (np.stack([c.column(f"{a}_{m}").to_numpy() for a in "xy"], 1) for m in ("min", "max"))
            blocks, qs = [], []
            for i, held in enumerate(c.column("blocks").to_pylist()):
                mine = np.flatnonzero(((shared.value[:, 1:3] <= high[i]) & (shared.value[:, 4:6] >= low[i])).all(1))
                blocks.append(np.repeat(np.array(held, np.int64), len(mine)))
                qs.append(np.tile(mine, len(held)))
            yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(blocks)), pa.array(np.concatenate(qs).astype(np.int64))], names=["block", "at"])

    pairs = b.cells().mapInArrow(run, "block long, at long").distinct()
    return pairs.groupBy("block").agg(F.collect_list("at").alias("qs"))  # as many as there are boxes at most


def counts_in_blocks(b: Blocks, boxes: DataFrame, where: Sequence[tuple[str, int, int]] = ()) -> DataFrame:
    """``q, n`` for every box; each block that some box leads to is decoded once, and tested with its boxes."""
    asked = _asked(boxes)
    shared = b.spark.sparkContext.broadcast(asked)
    names = [*"xyz", *dict.fromkeys(w[0] for w in where)]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for t in batches:
            for i in range(t.num_rows):
                got = {n: _sums(t.column(f"d_{n}")[i].as_py()) for n in names}
                q, n = count_each(shared.value[np.array(t.column("qs")[i].as_py())], got, where)
                yield pa.RecordBatch.from_arrays([pa.array(q), pa.array(n)], names=["q", "n"])

    rows = b.blocks().hint("merge").join(met_blocks(b, asked), "block").select("qs", *[f"d_{n}" for n in names])
    return _totals(boxes, rows.mapInArrow(run, "q long, n long"))


def candidate_blocks(b: Blocks, box: Box) -> DataFrame:
    """Blocks that a cell which meets the box in x and y leads to; the third axis is not indexed."""
    met = b.cells().where((F.col("x_min") <= box[3]) & (F.col("x_max") >= box[0]) & (F.col("y_min") <= box[4]) & (F.col("y_max") >= box[1]))
    return met.select(F.explode("blocks").alias("block")).distinct()


def decode(blocks: DataFrame, columns: Sequence[str]) -> DataFrame:
    """Whole blocks back to points."""
    names = ["x", "y", "z", *columns]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for i in range(b.num_rows):
                got = {n: _sums(b.column(f"d_{n}")[i].as_py()) for n in names}
                yield pa.RecordBatch.from_arrays([pa.array(got[n] if n in "xyz" else got[n].astype(np.int32)) for n in names], names=names)

    return blocks.select(*[f"d_{n}" for n in names]).mapInArrow(run, "x long, y long, z long" + "".join(f", {c} int" for c in columns))


def block_box(b: Blocks, box: Box, columns: Sequence[str] = (), where: Sequence[tuple[str, int, int]] = (), use_index: bool = True) -> DataFrame:
    blocks = b.blocks().join(candidate_blocks(b, box), "block", "left_semi") if use_index else b.blocks()
    need = list(dict.fromkeys([*columns, *[w[0] for w in where]]))
    return brute_box(decode(blocks, need), box, columns, where)


def block_work(b: Blocks, box: Box) -> DataFrame:
    """``blocks_decoded, points_decoded`` of a query."""
    return b.blocks().join(candidate_blocks(b, box), "block", "left_semi").agg(F.count("*").alias("blocks_decoded"), F.coalesce(F.sum("cnt"), F.lit(0)).alias("points_decoded"))


def write_sorted(points: DataFrame, parts: tuple[int, ...], path: str | None = None, files: int | None = None) -> str:
    """Spark's own way: Parquet in path order, pruned by the bounds of its row groups; as many files as shuffle partitions, or as asked for."""
    path = path or f"{shared_dir(points.sparkSession)}/sorted-{uuid.uuid4().hex}"
    points.withColumn("path", path_of(parts)).repartitionByRange(*([files] if files else []), "path").sortWithinPartitions("path").drop("path").write.option("parquet.block.size", 1 << 20).parquet(path)
    return path


def sorted_parquet_box(spark: SparkSession, path: str, box: Box, columns: Sequence[str] = ()) -> DataFrame:
    return brute_box(spark.read.parquet(path), box, columns)
