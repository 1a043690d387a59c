"""Tables written between rounds to cut lineage, in the shared folder the cluster names."""

from __future__ import annotations

import os
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession


def shared_root(spark: SparkSession) -> str:
    """The folder that ``spark.checkpoint.dir`` names; one of our own only where it is unset and all runs on one machine."""
    root = spark.conf.get("spark.checkpoint.dir", None)
    if root:
        return root
    if not spark.sparkContext.master.startswith("local["):
        raise RuntimeError("spark.checkpoint.dir must name a folder that all executors share")
    os.makedirs(f"{tempfile.gettempdir()}/checkpoints", exist_ok=True)
    return f"file://{tempfile.gettempdir()}/checkpoints"


#: A task that writes holds a row group: several tasks at once must fit in a heap.
ROW_GROUP = 16 << 20


class Rounds:
    """``keep`` writes a table and reads it back; ``drop`` removes one that no plan reads any more.

    With ``buckets``, rows with equal values of these columns lie in one bucket, as many
    as a shuffle has partitions: joins and sums by them need no shuffle.
    """

    def __init__(self, spark: SparkSession, name: str):
        self.spark = spark
        self.tag = uuid.uuid4().hex[:12]
        self.root = f"{shared_root(spark)}/{name}-{self.tag}"
        self.made: dict[str, str | None] = {}

    def keep(self, df: DataFrame, name: str, buckets: list[str] | None = None) -> DataFrame:
        path = f"{self.root}/{name}"
        if not buckets:
            self.made[name] = None
            df.write.mode("overwrite").option("parquet.block.size", ROW_GROUP).parquet(path)
            return self.spark.read.schema(df.schema).parquet(path)
        n = int(self.spark.conf.get("spark.sql.shuffle.partitions"))
        self.made[name] = table = f"rounds_{self.tag}_{name}".replace("-", "_")
        df.repartition(n, *buckets).write.mode("overwrite").option("parquet.block.size", ROW_GROUP).option("path", path).bucketBy(n, *buckets).sortBy(*buckets).saveAsTable(table)
        return self.spark.table(table)

    def drop(self, *names: str) -> None:
        for name in names:
            table = self.made.pop(name)
            if table:
                self.spark.sql(f"DROP TABLE IF EXISTS {table}")
            path = self.spark._jvm.org.apache.hadoop.fs.Path(f"{self.root}/{name}")
            path.getFileSystem(self.spark._jsc.hadoopConfiguration()).delete(path, True)

    def only(self, *names: str) -> None:
        """Drops all but these."""
        self.drop(*(n for n in list(self.made) if n not in names))
