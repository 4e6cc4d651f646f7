"""The given tables, the shared work folder, and readers and writers of maps."""

from __future__ import annotations

import itertools
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def work_folder(spark: SparkSession) -> str:
    """Folder that driver and executors share: spark.checkpoint.dir; a temporary one only on a local master."""
    base = spark.sparkContext.getConf().get("spark.checkpoint.dir") or spark.conf.get("spark.checkpoint.dir", None)
    if base:
        return base.rstrip("/")
    if spark.sparkContext.master == "local" or spark.sparkContext.master.startswith("local["):
        return f"file://{tempfile.mkdtemp(prefix='blockmatch-')}"
    return spark.conf.get("spark.sql.warehouse.dir").rstrip("/") + "/_blockmatch"


#: Rows of a small side (of about a kilobyte at most) that are sent to all tasks.
BROADCAST_ROWS = 20_000


def sent(df: DataFrame, n: int | None = None) -> DataFrame:
    """A side that is broadcast if it has few rows (n, or counted); beyond that the join shuffles."""
    return F.broadcast(df) if (df.count() if n is None else n) <= BROADCAST_ROWS else df


class Cuts:
    """Tables written between steps, so that lineage stays short and survives lost executors."""

    def __init__(self, spark: SparkSession, folder: str | None = None):
        self.spark, self.folder, self.n = spark, f"{folder or work_folder(spark)}/{uuid.uuid4().hex}", itertools.count(1)

    def scratch(self) -> Cuts:
        """A folder of its own for tables that are dropped together, with `close`."""
        return Cuts(self.spark, self.folder)

    def close(self) -> None:
        """Drop all tables of this folder."""
        path = self.spark._jvm.org.apache.hadoop.fs.Path(self.folder)
        path.getFileSystem(self.spark._jsc.hadoopConfiguration()).delete(path, True)

    def cut(self, df: DataFrame, name: str = "t") -> DataFrame:
        path = f"{self.folder}/{next(self.n):03d}-{name}"
        df.write.parquet(path)
        return self.spark.read.schema(df.schema).parquet(path)


#: Side of a tile of stored tables, in milli-units.
TILE = 64_000


def save_artifacts(art, folder: str, tile: int = TILE) -> None:
    """Write all tables of an artefact set, with what they were built for; homes and blocks lie in folders by tile, so a search near a place reads its tiles only."""
    at = lambda x, y: F.concat_ws("_", F.floor(F.col(x) / tile).cast("string"), F.floor(F.col(y) / tile).cast("string"))
    places = {"wide": ("x", "y"), "vertices": ("x", "y"), "blocks": ("xmin", "ymin")}
    for name, df in art.tables().items():
        if name in places:
            df = df.withColumn("tile", at(*places[name]))
            df.repartition("tile").sortWithinPartitions("tile", *places[name]).write.mode("overwrite").partitionBy("tile").parquet(f"{folder}/{name}")
        else:
            df.write.mode("overwrite").parquet(f"{folder}/{name}")
    about = [(art.radius, art.m, art.connected, art.fanout, art.packing)]
    art.spark.createDataFrame(about, "radius int, m int, connected boolean, fanout int, packing string").write.mode("overwrite").json(f"{folder}/about")


def load_artifacts(spark: SparkSession, folder: str, radius: int):
    """Read an artefact set back; one built for another radius is refused."""
    from ..plans.artifacts import TABLES, Artifacts

    about = spark.read.json(f"{folder}/about").first()
    if about["radius"] != radius:
        raise ValueError(f"the artefacts were built for radius {about['radius']}, not {radius}")
    tables = {t: spark.read.parquet(f"{folder}/{t}").drop("tile") for t in TABLES}
    return Artifacts(spark, radius=about["radius"], m=about["m"], connected=about["connected"], fanout=about["fanout"], packing=about["packing"], cut=Cuts(spark), **tables)


def read_edge_list_csv(spark: SparkSession, path: str) -> DataFrame:
    return spark.read.csv(path, schema="eid long, u long, v long", header=True)


def write_geojson(blocks: DataFrame, vertices: DataFrame, path: str) -> None:
    """One feature a line: the outline of each block with its kind."""
    corners = blocks.select("bid", "kind", F.posexplode("vids").alias("pos", "vid")).join(vertices, "vid")
    lines = corners.groupBy("bid", "kind").agg(F.array_sort(F.collect_list(F.struct("pos", "x", "y"))).alias("c"))
    shape = F.struct(F.lit("LineString").alias("type"), F.transform("c", lambda p: F.array(p["x"], p["y"])).alias("coordinates"))
    lines.select(F.to_json(F.struct(F.lit("Feature").alias("type"), shape.alias("geometry"), F.struct("bid", "kind").alias("properties"))).alias("value")).write.text(path)
