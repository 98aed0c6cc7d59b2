"""Run a streaming query over what is there now and read its result as a batch."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from wordlid.io import temporary


def stream(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """A table, which is one file or a folder of files, as a stream with an explicit schema."""
    path = f"{sf_dir}/{name}.parquet"
    found = spark._jvm.org.apache.hadoop.fs.Path(path)
    reader = spark.readStream.schema(spark.read.parquet(path).schema)
    if found.getFileSystem(spark._jsc.hadoopConfiguration()).getFileStatus(found).isDirectory():
        return reader.parquet(path)
    return reader.option("pathGlobFilter", f"{name}.parquet").parquet(sf_dir)


def event_stream(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Events with a time that watermarks accept; the stored time has no zone and is read as UTC."""
    return stream(spark, sf_dir, "events").withColumn("ts", F.expr("from_utc_timestamp(cast(ts as timestamp), current_timezone())"))


def run(df: DataFrame, mode: str = "append", key: list[str] | None = None) -> DataFrame:
    """Write the stream with availableNow. In update mode the last value of each key is the result;
    in complete mode each batch replaces the one before."""
    spark = df.sparkSession
    base = temporary(spark, "stream")
    out, schema = f"{base}/out", df.schema
    if mode == "append":
        q = df.writeStream.format("parquet").option("path", out).option("checkpointLocation", f"{base}/state").trigger(availableNow=True).start()
    else:
        how = "overwrite" if mode == "complete" else "append"

        def put(batch: DataFrame, number: int) -> None:
            batch.withColumn("_batch", F.lit(number)).write.mode(how).parquet(out)

        q = df.writeStream.outputMode(mode).foreachBatch(put).option("checkpointLocation", f"{base}/state").trigger(availableNow=True).start()
    q.awaitTermination()
    target = spark._jvm.org.apache.hadoop.fs.Path(out)
    if not target.getFileSystem(spark._jsc.hadoopConfiguration()).exists(target):  # no batch, as the stream has no files
        return spark.range(0).select(*[F.lit(None).cast(f.dataType).alias(f.name) for f in schema])
    if mode == "append":
        return spark.read.schema(schema).parquet(out)
    rows = spark.read.parquet(out)
    if mode == "update":
        rest = [c for c in schema.names if c not in key]
        rows = rows.groupBy(*key).agg(F.max_by(F.struct(*rest), "_batch").alias("_v")).select(*key, "_v.*")
    return rows.select(*schema.names)
