"""Where summaries are kept, shared folders, and a reader of signed event streams."""

from __future__ import annotations

import json
import tempfile
import uuid
from collections.abc import Iterator

from pyspark.sql import DataFrame, SparkSession

from balclust.functions.points import Grid
from balclust.operators.coreset import Summary
from balclust.plans.params import Params


def shared_dir(spark: SparkSession) -> str:
    """The folder that all executors share. Only a local master gets one of our own; on a cluster that names none this raises ValueError."""
    named = spark.conf.get("spark.checkpoint.dir", None)
    if named:
        return named.rstrip("/")
    if spark.sparkContext.getCheckpointDir() is None:
        if not spark.sparkContext.master.startswith("local"):
            raise ValueError("name a folder that driver and executors share in spark.checkpoint.dir")
        spark.sparkContext.setCheckpointDir(tempfile.mkdtemp(prefix="balclust-"))
    return spark.sparkContext.getCheckpointDir().rstrip("/")


def fresh(spark: SparkSession, what: str) -> str:
    return f"{shared_dir(spark)}/{what}-{uuid.uuid4().hex}"


def staged(df: DataFrame) -> DataFrame:
    """df written once and read back."""
    path = fresh(df.sparkSession, "staged")
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def save(summary: Summary, path: str) -> None:
    """Four tables: parameters, heavy cells, parts, and the sample by level."""
    spark = summary.coreset.sparkSession
    text = json.dumps({"params": summary.params._asdict(), "grid": summary.grid._asdict()})
    spark.sql("SELECT :text AS text", args={"text": text}).write.mode("overwrite").parquet(f"{path}/params")
    summary.heavy.write.mode("overwrite").parquet(f"{path}/heavy_cells")
    summary.parts.write.mode("overwrite").parquet(f"{path}/parts")
    summary.coreset.write.mode("overwrite").partitionBy("level").parquet(f"{path}/coreset")


def load(spark: SparkSession, path: str) -> Summary:
    held = json.loads(spark.read.parquet(f"{path}/params").first()[0])
    grid = Grid(held["grid"]["d"], held["grid"]["levels"], tuple(held["grid"]["shift"]))
    return Summary(Params(**held["params"]), grid, *(spark.read.parquet(f"{path}/{t}") for t in ("heavy_cells", "parts", "coreset")))


def register_signed_events(spark: SparkSession) -> None:
    """A batch source "signed_events" (options path, every): the events of a Parquet table as insertions, with a deletion of each whose number every divides.

    Tasks read the table themselves, a row group each: its path must be one that Arrow opens.
    """
    import pyarrow as pa
    import pyarrow.compute as pc
    import pyarrow.dataset as ds
    from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

    def opened(path: str):
        return ds.dataset(path.removeprefix("file://"), format="parquet") if path.startswith(("/", "file:///")) else ds.dataset(path, format="parquet")

    class Reader(DataSourceReader):
        def __init__(self, options: dict):
            self.path, self.every = options["path"], int(options.get("every", "5"))

        def partitions(self) -> list:
            return [InputPartition((k, g)) for k, f in enumerate(opened(self.path).get_fragments()) for g in range(len(f.row_groups))]

        def read(self, part: InputPartition) -> Iterator[pa.RecordBatch]:
            at, group = part.value
            fragment = list(opened(self.path).get_fragments())[at].subset(row_group_ids=[group])
            for b in fragment.to_batches(columns=["event_id", "value"]):
                number = b.column(0)
                gone = pc.equal(pc.subtract(number, pc.multiply(pc.divide(number, self.every), self.every)), 0)
                for rows, op in ((b, 1), (b.filter(gone), -1)):
                    yield pa.RecordBatch.from_arrays([rows.column(0).cast("int64"), pa.array([op] * len(rows), "int32"), rows.column(1).cast("float64")], ["event_id", "op", "value"])

    class Source(DataSource):
        @classmethod
        def name(cls) -> str:
            return "signed_events"

        def schema(self) -> str:
            return "event_id long, op int, value double"

        def reader(self, schema) -> DataSourceReader:
            return Reader(self.options)

    spark.dataSource.register(Source)


def read_back(df: DataFrame, kind: str, **options) -> DataFrame:
    """df written in a format and read again with its own schema."""
    path = fresh(df.sparkSession, kind)
    df.write.format(kind).options(**options).save(path)
    return df.sparkSession.read.schema(df.schema).format(kind).options(**options).load(path)
