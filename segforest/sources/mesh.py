"""Export of element meshes as plain tables: one row an element with its corners and a value to colour it by."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import StructType

from ..operators.forest import shared_folder


def mesh_rows(leaves: DataFrame, top: int, colour: str = "pid") -> DataFrame:
    """tree, level, key, x0..z1 in the unit cube, colour (the owner, say, or the level)."""
    from ..plans.pipeline import boxes

    b = boxes(leaves, top)
    return b.select("tree", "level", "key", *[f"{c}{s}" for s in (0, 1) for c in "xyz"], F.col(colour).alias("colour"))


def export_mesh(leaves: DataFrame, path: str, top: int, colour: str = "pid", fmt: str = "parquet", files: int = 8) -> None:
    """Writes mesh_rows in curve order, in ``files`` ranges of the curve, as parquet, csv or json."""
    rows = mesh_rows(leaves, top, colour)
    rows.repartitionByRange(files, "tree", "key").sortWithinPartitions("tree", "key").write.mode("overwrite").format(fmt).options(**({"header": "true"} if fmt == "csv" else {})).save(path)


def write_forest(leaves: DataFrame, path: str | None = None, files: int = 8) -> str:
    """Leaves and payload in ``files`` ranges of the curve, in curve order, a folder a tree: readers skip trees by folder and keys by the files' least and
    greatest. Without ``path`` below the folder that all executors share. Returns the path."""
    import uuid

    path = path or f"{shared_folder(leaves.sparkSession)}/forest-{uuid.uuid4().hex}"
    leaves.repartitionByRange(files, "tree", "key").sortWithinPartitions("tree", "key").write.partitionBy("tree").parquet(path)
    return path


def read_forest(spark: SparkSession, path: str, schema: StructType) -> DataFrame:
    return spark.read.schema(schema).parquet(path)


def bucketed(df: DataFrame, name: str, keys: list[str], buckets: int) -> DataFrame:
    """``df`` as a table in the warehouse, in buckets of ``keys``, each sorted by them; a table of that name is replaced."""
    df.write.mode("overwrite").bucketBy(buckets, *keys).sortBy(*keys).option("path", f"{shared_folder(df.sparkSession)}/tables/{name}").saveAsTable(name)
    return df.sparkSession.table(name)
