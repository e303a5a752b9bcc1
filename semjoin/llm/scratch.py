"""Written intermediate tables, the same as the engine's, and the size of what goes to Python workers."""

from pyspark.sql import SparkSession

from semjoin.state import Scratch, delete, shared_root

__all__ = ["Scratch", "delete", "shared_root", "small_batches"]

ROWS = 1000  # texts of some KB each: a few MB a batch, of which an executor and its workers hold several
_BATCH = "spark.sql.execution.arrow.maxRecordsPerBatch"


def small_batches(spark: SparkSession) -> None:
    """Lowers the session's rows per Arrow batch (a setting of the running session) to what texts need; a lower one stays."""
    now = int(spark.conf.get(_BATCH))
    if now <= 0 or now > ROWS:
        spark.conf.set(_BATCH, str(ROWS))
