"""A ledger of charged releases: Parquet rows, one an idempotent charge. A release id is charged once."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.noise import Noise
from ..sources.tables import write_release
from .accounting import Budget
from .planner import ReleaseSpec

SCHEMA = "release_id string, folds long, per_query_eps double, per_query_delta double, total_eps double, total_delta double, method string, constraint_id string"


class Overspent(ValueError):
    pass


class Busy(RuntimeError):
    pass


class Ledger:
    """Charges are serialised by a lock file that the file system creates at most once; what crashed while it held the lock must
    be looked at before the lock is removed by hand (`unlock`)."""

    def __init__(self, spark: SparkSession, folder: str, limit: Budget):
        self.spark, self.folder, self.limit = spark, folder, limit
        self._path = spark._jvm.org.apache.hadoop.fs.Path
        self._fs = self._path(folder).getFileSystem(spark._jsc.hadoopConfiguration())

    def rows(self) -> DataFrame:
        if not self._fs.globStatus(self._path(self.folder + "/*/part-*")):  # nothing charged yet
            return self.spark.createDataFrame([], SCHEMA)
        return self.spark.read.schema(SCHEMA).parquet(self.folder + "/*/part-*")

    def spent(self) -> Budget:
        r = self.rows().agg(F.coalesce(F.sum("total_eps"), F.lit(0.0)), F.coalesce(F.sum("total_delta"), F.lit(0.0))).first()
        return Budget(r[0], r[1])

    def remaining(self) -> Budget:
        s = self.spent()
        return Budget(max(0.0, self.limit.eps - s.eps), max(0.0, self.limit.delta - s.delta))

    def _lock(self):
        return self._path(self.folder + "/_lock")

    def unlock(self) -> None:
        self._fs.delete(self._lock(), False)

    def charge(self, release_id: str, folds: int, per_query: Budget, method: str = "basic", constraint: str = "") -> None:
        """Refuses what is beyond the limit, and a release id that is charged already. One charge at a time: a second writer gets
        Busy and may try again."""
        total = Budget(folds * per_query.eps, folds * per_query.delta)
        self._fs.mkdirs(self._path(self.folder))
        if not self._fs.createNewFile(self._lock()):
            raise Busy(f"{self.folder} is being charged")
        try:
            left = self.remaining()
            if total.eps > left.eps + 1e-12 or total.delta > left.delta + 1e-18:
                raise Overspent(f"{release_id} needs {total}, {left} is left")
            row = [(release_id, folds, per_query.eps, per_query.delta, total.eps, total.delta, method, constraint)]
            self.spark.createDataFrame(row, SCHEMA).coalesce(1).write.mode("errorifexists").parquet(f"{self.folder}/{release_id}")
        finally:
            self.unlock()

    def charge_spec(self, spec: ReleaseSpec, per_query: Budget, folds: int | None, method: str = "basic", slack: float = 0.0) -> Budget:
        """Charge what a release promises under its name: its folds, or all its queries where nothing bounds them. An endless
        release without folds, and optimal composition of an adaptive one, are refused before anything is charged."""
        total = spec.budget(per_query, folds, method, slack)
        self.charge(spec.name, 1, total, method)
        return total

    def release(self, release_id: str, folds: int, noise: Noise, publish: Callable[[Noise], DataFrame], path: str, constraint: str = "") -> DataFrame:
        """Charge, then publish and write under path; nothing is computed that isn't paid for. publish(noise) is the release."""
        self.charge(release_id, folds, Budget(noise.eps, noise.delta), constraint=constraint)
        write_release(publish(noise), path, release_id=release_id)
        return self.spark.read.parquet(f"{path}/release={release_id}")
