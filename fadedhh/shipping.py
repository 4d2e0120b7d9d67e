"""Sends this package to the executors, which need not see the driver's source tree."""

from __future__ import annotations

import tempfile
import zipfile
from contextlib import contextmanager
from pathlib import Path

from pyspark.sql import DataFrame, SparkSession

_sent: set[str] = set()


def ensure_shipped(spark: SparkSession) -> None:
    """Adds a zip of the package to the session, once per application."""
    context = spark.sparkContext
    if context.applicationId in _sent:
        return
    top = Path(__file__).resolve().parent
    path = Path(tempfile.mkdtemp(prefix="ship-")) / "fadedhh_src.zip"
    with zipfile.ZipFile(path, "w") as z:
        for f in sorted(top.rglob("*.py")):
            z.write(f, str(f.relative_to(top.parent)))
    context.addPyFile(str(path))
    _sent.add(context.applicationId)


def arrow_map(df: DataFrame, function, schema: str) -> DataFrame:
    """``mapInArrow`` of a function of this package, whoever made ``df``."""
    ensure_shipped(df.sparkSession)
    return df.mapInArrow(function, schema)


@contextmanager
def fixed_width(spark: SparkSession):
    """For jobs that hand rows of a few numbers to Python: batches are bounded by rows alone. Bounded by bytes too, the engine
    measures the batch anew after every row, which costs more than the rest of the hand-over and hardly gains from more cores.
    Settings are put back at the end, so jobs on texts keep their bound in bytes."""
    wanted = {"spark.sql.execution.arrow.maxBytesPerBatch": str((1 << 31) - 1), "spark.sql.execution.arrow.maxRecordsPerBatch": str(1 << 16)}
    before = {k: spark.conf.get(k, None) for k in wanted}
    try:
        for k, v in wanted.items():
            spark.conf.set(k, v)
        yield
    finally:
        for k, v in before.items():
            spark.conf.unset(k) if v is None else spark.conf.set(k, v)
