"""The prepared store: equi-depth slabs on disk, sorted by time, with their bounds, tree and numbering.

Preparation is done once for a data set and free of the join's parameters. A query reads a slab's own
rows as stored and the halo from the neighbouring slabs by ranges of t, which Parquet prunes: no shuffle.
"""

from __future__ import annotations

import bisect
import json
from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

from ..params import JoinParams
from ..plans import partitioning, quadtree
from ..plans.partitioning import Slabs
from ..plans.quadtree import Quadtree
from ..points import with_sequence
from .scratch import remove, scratch, shuffles_dropped


@dataclass(frozen=True)
class PreparedStore:
    path: str
    slabs: Slabs
    tree: Quadtree

    def points(self, spark: SparkSession) -> DataFrame:
        """All points, numbered. The samples before and after, which ``with_sequence`` adds, are not stored but looked up by
        number, at the cost of a shuffle where a query uses them."""
        w, own = Window.partitionBy("traj").orderBy("seq"), spark.read.schema(f"{STORED}, slab int").parquet(f"{self.path}/points")
        return own.select("*", *[f(c).over(w).alias(f"{k}_{c}") for k, f in (("prev", F.lag), ("next", F.lead)) for c in ("t", "x", "y")])


STORED = "traj long, t long, x double, y double, pid long, seq long"
ROW_BYTES, BLOCK_BYTES, LEAST_SLABS = 48, 128 << 20, 16
"""Bytes of a point, and of a slab, which one task reads and sweeps."""


def prepare(pts: DataFrame, path: str, m: int | None = None, cap_fraction: float = 0.03, n_nodes: int = 1) -> PreparedStore:
    """Numbers the points, finds bounds and tree, writes slabs and a manifest.

    m slabs, or as many as hold a block each (``LEAST_SLABS`` at least). A slab is written by one task, sorted by
    time, as one file with small row groups, so that a neighbour's halo is read by the statistics of t.

    Numbered points are written to the shared folder in between, and removed at the end: all else is found from them, and
    the files of the shuffle by trajectory are gone before the one by slab begins."""
    spark = pts.sparkSession
    held = scratch(spark, "numbered")
    with shuffles_dropped(spark):
        with_sequence(pts).select("traj", "t", "x", "y", "pid", "seq").write.option("compression", "zstd").parquet(held)
    numbered = spark.read.schema(STORED).parquet(held)
    if m is None:
        m = max(LEAST_SLABS, partitioning.plan_slabs(numbered.count() * ROW_BYTES, BLOCK_BYTES, n_nodes)[0])
    slabs, tree = partitioning.equi_depth(numbered, m), quadtree.build(numbered, cap_fraction)
    sorted_ = numbered.withColumn("slab", slabs.of(F.col("t"))).repartitionById(slabs.count, "slab").sortWithinPartitions("slab", "t", "pid")
    with shuffles_dropped(spark):
        sorted_.write.option("parquet.block.size", 8 << 20).option("compression", "zstd").partitionBy("slab").parquet(f"{path}/points")
    remove(spark, held)
    manifest = json.dumps({"bounds": slabs.bounds, "box": [tree.x0, tree.y0, tree.x1, tree.y1], "leaves": tree.leaves})
    pts.sparkSession.createDataFrame([(manifest,)], "manifest string").coalesce(1).write.text(f"{path}/manifest")
    return PreparedStore(path, slabs, tree)


def load(spark: SparkSession, path: str) -> PreparedStore:
    found = json.loads(spark.read.text(f"{path}/manifest").first()[0])
    return PreparedStore(path, Slabs(tuple(found["bounds"])), Quadtree(*found["box"], tuple(tuple(leaf) for leaf in found["leaves"])))


class _Slab(InputPartition):
    def __init__(self, slab: int, lo: int | None, hi: int | None):
        self.slab, self.lo, self.hi = slab, lo, hi


def opened(path: str):
    """File system and path of a URI or plain path, on the driver or an executor."""
    from pyarrow import fs

    if path.startswith("file:"):
        path = "/" + path.removeprefix("file:").lstrip("/")
    return (fs.LocalFileSystem(), path) if path.startswith("/") else fs.FileSystem.from_uri(path)


class _SlabReader(DataSourceReader):
    """One input partition for each slab: its own rows and those of the neighbours within eps of its range, by time."""

    def __init__(self, options: dict):
        self.path, self.eps = options["path"], int(options["epst"])
        self.slabs = Slabs(tuple(int(b) for b in options["bounds"].split(",") if b))

    def partitions(self):
        return [_Slab(*limits) for limits in self.slabs.limits()]

    def read(self, part: _Slab):
        import pyarrow as pa
        import pyarrow.dataset as ds
        from pyarrow import fs

        cols = ["traj", "seq", "t", "x", "y", "pid"]
        where, path = opened(self.path)
        edges = self.slabs.bounds
        # the slabs that the widened range meets, mostly the one before, this one and the one after
        first = 0 if part.lo is None else bisect.bisect_right(edges, part.lo - self.eps)
        last = len(edges) if part.hi is None else bisect.bisect_right(edges, part.hi + self.eps - 1)
        for slab in range(first, last + 1):
            folder = f"{path}/points/slab={slab}"
            if where.get_file_info(folder).type != fs.FileType.Directory:
                continue
            keep = None
            if slab < part.slab:
                keep = ds.field("t") >= part.lo - self.eps
            elif slab > part.slab:
                keep = ds.field("t") < part.hi + self.eps
            rows = ds.dataset(folder, filesystem=where, format="parquet").to_table(columns=cols, filter=keep)
            for batch in rows.sort_by([("t", "ascending"), ("pid", "ascending")]).combine_chunks().to_batches(max_chunksize=10_000):
                home = pa.array([slab == part.slab] * batch.num_rows)
                yield pa.RecordBatch.from_arrays([*[batch[c] for c in cols], home, pa.array([part.slab] * batch.num_rows, pa.int32())], names=[*cols, "is_home", "slab"])


class HaloSource(DataSource):
    """spark.read.format("halo"): self-sufficient slabs, a partition each, in order of time (options path, epst,
    bounds). Each reads the files of its own and its neighbouring slabs alone, through Arrow's file systems."""

    @classmethod
    def name(cls) -> str:
        return "halo"

    def schema(self) -> str:
        return "traj long, seq long, t long, x double, y double, pid long, is_home boolean, slab int"

    def reader(self, schema):
        return _SlabReader(self.options)


def halo(spark: SparkSession, store: PreparedStore, params: JoinParams) -> DataFrame:
    spark.dataSource.register(HaloSource)
    return spark.read.format("halo").option("path", store.path).option("epst", str(params.eps_t_us)).option("bounds", ",".join(map(str, store.slabs.bounds))).load()
