"""Tables of a data folder, and the append-only answer cache."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def table(spark: SparkSession, folder: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{folder}/{name}.parquet")


ANSWERS = "k binary, value string, status string, in_tokens int, out_tokens int, valid boolean, calls int"


class AnswerCache:
    """Committed answers as Parquet, one folder per call site: a restarted job never pays twice."""

    def __init__(self, spark: SparkSession, folder: str):
        self.spark, self.folder = spark, folder

    def _path(self, site: str) -> str:
        return f"{self.folder}/site={site}"

    def read(self, site: str) -> DataFrame | None:
        path = self.spark._jvm.org.apache.hadoop.fs.Path(self._path(site))
        if not path.getFileSystem(self.spark._jsc.hadoopConfiguration()).exists(path):
            return None
        return self.spark.read.schema(ANSWERS).parquet(self._path(site)).where(F.col("status") == "ok").dropDuplicates(["k"])

    def append(self, site: str, answers: DataFrame) -> None:
        answers.select("k", "value", "status", "in_tokens", "out_tokens", "valid", "calls").write.mode("append").parquet(self._path(site))
