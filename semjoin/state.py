"""Tables written in the shared folder, which cut lineage and outlive lost executors.

The folder is the session's ``spark.checkpoint.dir``.  Only where that is unset and everything runs
in one process (as in tests) a temporary folder of this process is used; elsewhere that raises.
What is written goes with ``Scratch.close``, ``release_all`` or the end of the process; a killed driver
leaves its folders (named by the run), which may be deleted at any time after it.
"""

from __future__ import annotations

import atexit
import shutil
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession

_own: list[str] = []
_bases: list[tuple[SparkSession, str]] = []


def shared_root(spark: SparkSession) -> str:
    root = spark.conf.get("spark.checkpoint.dir", None)
    if root:
        return root
    master = spark.sparkContext.master
    if not (master == "local" or master.startswith("local[")):
        raise RuntimeError("set spark.checkpoint.dir to a folder that all machines share")
    if not _own:
        _own.append(tempfile.mkdtemp(prefix="semjoin-"))
        atexit.register(shutil.rmtree, _own[0], ignore_errors=True)
    return f"file://{_own[0]}"


def _fs(spark: SparkSession, path: str):
    p = spark._jvm.org.apache.hadoop.fs.Path(path)
    return p.getFileSystem(spark._jsc.hadoopConfiguration()), p


def exists(spark: SparkSession, path: str) -> bool:
    fs, p = _fs(spark, path)
    return fs.exists(p)


def delete(spark: SparkSession, path: str) -> None:
    fs, p = _fs(spark, path)
    fs.delete(p, True)


def release_all() -> None:
    """Deletes everything that this process has written and not named to be resumed."""
    while _bases:
        spark, base = _bases.pop()
        try:
            delete(spark, base)
        except Exception:  # noqa: BLE001 - the session has ended; its folder is left
            return


atexit.register(release_all)


class Scratch:
    """Written intermediate tables of one run of an operator.

    With ``resume``, a folder of the caller's, tables that a run before has finished under the same
    number and name are read and not made again; the caller deletes it.
    """

    def __init__(self, spark: SparkSession, name: str, resume: str | None = None):
        self.spark = spark
        self.resume = resume
        self.base = resume.rstrip("/") if resume else f"{shared_root(spark).rstrip('/')}/{name}-{uuid.uuid4().hex[:12]}"
        if not resume:
            _bases.append((spark, self.base))
        self._n = 0

    def table(self, df: DataFrame, name: str = "t") -> DataFrame:
        """Write ``df`` once; what is returned reads the files."""
        self._n += 1
        path = f"{self.base}/{self._n}-{name}"
        if not (self.resume and exists(self.spark, f"{path}/_SUCCESS")):
            df.write.mode("overwrite").parquet(path)
        out = self.spark.read.schema(df.schema).parquet(path)
        out._scratch_path = path
        return out

    def drop(self, *tables: DataFrame) -> None:
        """Delete tables that nothing reads any more."""
        for t in tables:
            path = getattr(t, "_scratch_path", None)
            if path:
                delete(self.spark, path)

    def close(self) -> None:
        """Delete all tables; what reads them must be done."""
        delete(self.spark, self.base)
