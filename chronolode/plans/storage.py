"""Tables written between steps, in the folder that all executors share."""

from __future__ import annotations

import atexit
import uuid
from collections.abc import Callable, Iterator
from contextlib import contextmanager
from contextvars import ContextVar
from functools import wraps

from py4j.protocol import Py4JError
from pyspark.sql import DataFrame, SparkSession

_INSIDE: ContextVar[str | None] = ContextVar("folder of the running job", default=None)


#: Paths that this process has made and not deleted yet; they go when it ends.
_MADE: set[str] = set()


def folder(spark: SparkSession, name: str = "mining") -> str:
    """A new path below spark.checkpoint.dir, or below the warehouse where the session names none: never a machine's own temporary folder."""
    base = _INSIDE.get() or spark.conf.get("spark.checkpoint.dir", None) or spark.conf.get("spark.sql.warehouse.dir")
    path = f"{base.rstrip('/')}/{name}-{uuid.uuid4().hex}"
    if not _INSIDE.get():
        _MADE.add(path)
    return path


def delete(spark: SparkSession, path: str) -> None:
    where = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    where.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(where, True)
    _MADE.discard(path)


@atexit.register
def _delete_all() -> None:
    """Lazy results read their tables until the process ends; a session that has been stopped leaves them to the folder's owner."""
    spark = SparkSession.getActiveSession()
    try:
        for path in list(_MADE) if spark else ():
            delete(spark, path)
    except (Py4JError, OSError):  # the JVM has gone first
        pass


@contextmanager
def scratch(spark: SparkSession) -> Iterator[str]:
    """Tables written in this block are deleted at its end: for runs whose result does not read them."""
    path = folder(spark)
    token = _INSIDE.set(path)
    try:
        yield path
    finally:
        _INSIDE.reset(token)
        delete(spark, path)


def scratched(run: Callable) -> Callable:
    """A function of a sequence whose written tables go when it returns."""

    @wraps(run)
    def inside(ces: DataFrame, *args, **more):  # noqa: ANN002, ANN003, ANN202
        with scratch(ces.sparkSession):
            return run(ces, *args, **more)

    return inside


def written(df: DataFrame) -> DataFrame:
    """The rows as a table: lineage ends here, and later jobs read it whichever executors are lost."""
    path = folder(df.sparkSession)
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)
