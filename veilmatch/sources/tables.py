"""Tables and registries from files and databases, with declared schemas."""

from __future__ import annotations

import os
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import types as T

REGISTRY = T.StructType(
    [
        T.StructField("rec_id", T.LongType()),
        T.StructField("owner", T.StringType()),
        *[T.StructField(n, T.StringType()) for n in ("first_name", "last_name", "birth_name", "city")],
        *[T.StructField(n, T.IntegerType()) for n in ("postcode", "birth_year", "birth_month", "birth_day")],
    ]
)


def table(spark: SparkSession, folder: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{folder}/{name}.parquet")


def shared_folder(spark: SparkSession) -> str:
    """The folder that the cluster shares (spark.checkpoint.dir); a local master without one uses this machine's."""
    context = spark.sparkContext
    folder = context.getConf().get("spark.checkpoint.dir")
    if not folder:
        if not context.master.startswith("local"):
            raise RuntimeError("spark.checkpoint.dir must name a folder that driver and executors share")
        folder = os.path.join(tempfile.gettempdir(), "veilmatch-checkpoints")
    return folder.rstrip("/")


def stored(df: DataFrame) -> DataFrame:
    """``df`` written as Parquet in the shared folder and read again; the files go when the driver ends.

    Frames that many plans read are written, not cached: a cached frame hangs its own plan, with those of all
    cached frames below it, in every plan above, and each query walks them all; a lost executor
    would have them computed anew.
    """
    spark = df.sparkSession
    path = f"{shared_folder(spark)}/stored-{uuid.uuid4().hex}"
    place = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    place.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).deleteOnExit(place)
    df.write.parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def checked(df: DataFrame, schema: T.StructType = REGISTRY) -> DataFrame:
    """The columns of the schema; an error names what is missing or of another type."""
    have = dict(df.dtypes)
    wrong = [f"{f.name} {f.dataType.simpleString()}" for f in schema.fields if have.get(f.name) != f.dataType.simpleString()]
    if wrong:
        raise ValueError(f"columns wanted: {', '.join(wrong)}")
    return df.select(*schema.fieldNames())


def registry(spark: SparkSession, path: str, kind: str = "parquet", schema: T.StructType = REGISTRY, **options: str) -> DataFrame:
    """A registry file (parquet, orc, json, csv); unreadable rows of text formats are kept in ``_corrupt``."""
    if kind in ("json", "csv"):
        wide = T.StructType([*schema.fields, T.StructField("_corrupt", T.StringType())])
        return spark.read.schema(wide).options(mode="PERMISSIVE", columnNameOfCorruptRecord="_corrupt", **options).format(kind).load(path)
    return checked(spark.read.options(**options).format(kind).load(path), schema)


def jdbc(spark: SparkSession, url: str, name: str, column: str, low: int, high: int, parts: int, **properties: str) -> DataFrame:
    """A registry in a database, read in ranges of a key column."""
    return checked(spark.read.jdbc(url, name, column=column, lowerBound=low, upperBound=high, numPartitions=parts, properties=properties))


def write_links(links: DataFrame, path: str, by: str = "owner") -> None:
    """Overwrites only the partitions that the links have, so that a repeated run changes nothing."""
    links.write.mode("overwrite").option("partitionOverwriteMode", "dynamic").partitionBy(by).parquet(path)
