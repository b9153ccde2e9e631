"""Where intermediate results go, and how iteration cuts its lineage.

Every loop of the engine materialises through this module, so that one setting
(``spark.checkpoint.dir``, read from the session) decides the place.  Nothing
here uses ``localCheckpoint``: a lost executor must never lose a round.
"""

from __future__ import annotations

import tempfile
import uuid
from collections.abc import Iterator
from contextlib import contextmanager

from pyspark.sql import DataFrame, SparkSession

_own_dirs: dict[str, str] = {}
_scopes: list[list[str]] = []


def shared_dir(spark: SparkSession) -> str:
    """The folder that all executors share.

    It is ``spark.checkpoint.dir`` of the session.  Where that is unset, a cluster
    uses a folder in its warehouse; only a session on one machine, as in tests,
    makes a temporary folder, once.
    """
    configured = spark.conf.get("spark.checkpoint.dir", None)
    if configured:
        return configured.rstrip("/")
    app = spark.sparkContext.applicationId
    if app not in _own_dirs:
        if spark.sparkContext.master.startswith("local"):
            _own_dirs[app] = "file://" + tempfile.mkdtemp(prefix="pathalgebra-")
        else:
            _own_dirs[app] = f"{spark.conf.get('spark.sql.warehouse.dir').rstrip('/')}/pathalgebra-{app}"
    return _own_dirs[app]


def fresh_path(spark: SparkSession, name: str) -> str:
    """A path in the shared folder that nobody has used before."""
    return f"{shared_dir(spark)}/{name}-{uuid.uuid4().hex}"


def delete_paths(spark: SparkSession, paths: list[str]) -> None:
    """Remove folders by the file system they lie in; missing ones don't matter."""
    hadoop = spark.sparkContext._jvm.org.apache.hadoop.fs
    for p in paths:
        path = hadoop.Path(p)
        path.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(path, True)


@contextmanager
def scratch(spark: SparkSession) -> Iterator[None]:
    """Deletes at its end what ``stored`` wrote inside.

    What outlives the block must have been written before it ends and outside of
    it, as by :func:`kept`.  After an error the files stay for a look at them.
    """
    _scopes.append([])
    try:
        yield
    except BaseException:
        _scopes.pop()
        raise
    delete_paths(spark, _scopes.pop())


def stored(df: DataFrame, name: str = "step") -> DataFrame:
    """Write a frame as Parquet in the shared folder and read it back.

    This cuts the lineage, survives the loss of any executor and gives the
    optimizer a true size, so that later joins may broadcast what is small.
    The order and the number of partitions aren't kept.
    """
    spark = df.sparkSession
    path = fresh_path(spark, name)
    df.write.parquet(path)
    if _scopes:
        _scopes[-1].append(path)
    return spark.read.schema(df.schema).parquet(path)


def kept(df: DataFrame, name: str = "result") -> DataFrame:
    """Like ``stored``, for the result of a :func:`scratch` block: the block around that one owns it."""
    inner = _scopes.pop()
    try:
        return stored(df, name)
    finally:
        _scopes.append(inner)


def checkpointed(df: DataFrame) -> DataFrame:
    """Reliable checkpoint: cuts the lineage and keeps partitions as they are."""
    spark = df.sparkSession
    if not spark.conf.get("spark.checkpoint.dir", None):
        spark.sparkContext.setCheckpointDir(shared_dir(spark))
    return df.checkpoint(eager=True)


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """One of the given tables."""
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")
