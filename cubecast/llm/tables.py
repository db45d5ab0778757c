"""What the operators share: sessions, tables in the shared folder, identifiers, rows that go and rows that stay."""

import os
import tempfile
import uuid

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: Stands for a null identifier: larger than all others.
LAST = 2**63 - 1
BATCH_BYTES = 4 << 20
CLEAN_UP = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"


def small_batches(spark: SparkSession) -> None:
    """Arrow batches of a few MB: long texts would otherwise make batches of 64 MB, held in the JVM and in Python at once."""
    spark.conf.set("spark.sql.execution.arrow.maxBytesPerBatch", str(BATCH_BYTES))


def read(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    small_batches(spark)
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def partitions(spark: SparkSession) -> int:
    return int(spark.conf.get("spark.sql.shuffle.partitions"))


def named(name: str) -> Column:
    """A column by its whole name, whatever characters it holds."""
    return F.col("`" + name.replace("`", "``") + "`")


def ident(name: str = "doc_id") -> Column:
    return F.coalesce(named(name).cast("long"), F.lit(LAST))


def unident(name: str) -> Column:
    return F.when(F.col(name) != F.lit(LAST), F.col(name))


def unused(docs: DataFrame, name: str) -> str:
    """A column name that the table doesn't have, in any case."""
    taken = {c.lower() for c in docs.columns}
    while name in taken:
        name += "_"
    return name


def row_key(docs: DataFrame) -> Column:
    """128 bits of a row's whole content: equal for equal rows, whatever their identifiers."""
    return F.unhex(F.md5(F.to_json(F.struct(*map(named, docs.columns)), {"ignoreNullFields": "false"})))


def without(docs: DataFrame, keys: DataFrame) -> DataFrame:
    """docs less the rows whose key has ``gone`` set; of equal rows whose key has it unset, one stays. keys: key, gone."""
    name = unused(docs, "row_key")
    keyed = docs.withColumn(name, row_key(docs))
    keys = shared_table(keys.withColumnRenamed("key", name))  # read twice
    out = keyed.join(keys.select(name).distinct(), name, "left_anti").drop(name)
    many = keys.where(~F.col("gone")).select(name).distinct()
    if many.isEmpty():
        return out.select(*map(named, docs.columns))
    one = keyed.join(many, name, "left_semi").dropDuplicates([name]).drop(name)
    return out.unionByName(one).select(*map(named, docs.columns))


def shared_folder(spark: SparkSession) -> str:
    """The folder that all executors share. A local one only where none is set and all runs on this machine."""
    place = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if not place:
        if not spark.sparkContext.master.startswith("local") or spark.sparkContext.master.startswith("local-"):
            raise ValueError("set spark.checkpoint.dir to a folder that all executors share")
        place = os.path.join(tempfile.gettempdir(), "cubecast-checkpoints")
    return place


def shared_table(df: DataFrame) -> DataFrame:
    """df by way of a table in the shared folder: computed once, compressed, readable after an executor is lost.

    What was shuffled for it is removed when it is written. The table stays until ``forget``, or for the folder's clean-up.
    """
    spark = df.sparkSession
    where = f"{shared_folder(spark)}/table-{uuid.uuid4().hex}"
    before = spark.conf.get(CLEAN_UP, "false")
    spark.conf.set(CLEAN_UP, "true")
    try:
        df.select("*").write.parquet(where)
    finally:
        spark.conf.set(CLEAN_UP, before)
    return spark.read.schema(df.schema).parquet(where)


def forget(table: DataFrame) -> None:
    """Deletes a table of ``shared_table`` that nothing reads any more."""
    spark = table.sparkSession
    for file in table.inputFiles()[:1]:
        path = spark._jvm.org.apache.hadoop.fs.Path(file).getParent()
        if path.getName().startswith("table-"):
            path.getFileSystem(spark._jsc.hadoopConfiguration()).delete(path, True)
