"""What has been spent of a privacy budget, as a table in a shared folder."""

from __future__ import annotations

from pyspark.sql import SparkSession
from pyspark.sql import functions as F


class BudgetExceeded(ValueError):
    pass


class Ledger:
    """Charges releases to a total (eps, delta); charges add up, and a name is charged once."""

    def __init__(self, spark: SparkSession, folder: str, eps: float, delta: float):
        self.spark, self.folder, self.eps, self.delta = spark, folder.rstrip("/"), eps, delta

    def entries(self):
        """(name, eps, delta) of all charges."""
        schema = "name string, eps double, delta double"
        path = self.spark.sparkContext._jvm.org.apache.hadoop.fs.Path(self.folder)
        if not path.getFileSystem(self.spark.sparkContext._jsc.hadoopConfiguration()).exists(path):
            return self.spark.createDataFrame([], schema)
        return self.spark.read.schema(schema).parquet(self.folder)

    def spent(self) -> tuple[float, float]:
        row = self.entries().agg(F.sum("eps"), F.sum("delta")).first()
        return float(row[0] or 0), float(row[1] or 0)

    def spend(self, name: str, eps: float, delta: float) -> None:
        """Enters a release before it is made; a name that was charged already costs nothing again."""
        if self.entries().where(F.col("name") == name).count():
            return
        used = self.spent()
        if used[0] + eps > self.eps * (1 + 1e-12) or used[1] + delta > self.delta * (1 + 1e-12):
            raise BudgetExceeded(f"{name} asks for ({eps}, {delta}); ({self.eps - used[0]}, {self.delta - used[1]}) is left")
        self.spark.createDataFrame([(name, float(eps), float(delta))], "name string, eps double, delta double").coalesce(1).write.mode("append").parquet(self.folder)
