"""Session helpers: test sessions, shared scratch space and code shipping.

Nothing here changes settings that are fixed when a session starts; every function works with the session it is
given.
"""

from __future__ import annotations

import functools
import gc
import os
import tempfile
import uuid
import zipfile
from collections.abc import Callable
from contextvars import ContextVar
from pathlib import Path

from pyspark.sql import DataFrame, SparkSession

_SHIPPED: set[str] = set()
#: Tables made in the scopes that are open, innermost last; each thread has scopes of its own.
_SCOPES: ContextVar[tuple[list[DataFrame], ...]] = ContextVar("scopes", default=())


def local_session(app: str = "pullgraph", cores: str = "8", partitions: int = 8) -> SparkSession:
    """A local session for tests and the bench."""
    return (
        SparkSession.builder.master(f"local[{cores}]")
        .appName(app)
        .config("spark.sql.shuffle.partitions", str(partitions))
        .config("spark.driver.memory", os.environ.get("PULLGRAPH_DRIVER_MEMORY", "12g"))
        .config("spark.sql.session.timeZone", "UTC")
        .config("spark.ui.enabled", "false")
        .config("spark.ui.showConsoleProgress", "false")
        .getOrCreate()
    )


def ship(spark: SparkSession) -> None:
    """Give this package to the Python workers once per application.

    Python functions are pickled by module name, so that a worker that is reused keeps its module-level caches.  The
    zip travels through the driver's own file server; no shared folder is needed.
    """
    app = spark.sparkContext.applicationId
    if app in _SHIPPED:
        return
    root = Path(__file__).resolve().parent
    target = Path(tempfile.mkdtemp(prefix="pullgraph-ship-")) / "pullgraph_code.zip"
    with zipfile.ZipFile(target, "w", zipfile.ZIP_DEFLATED) as z:
        for p in sorted(root.rglob("*.py")):
            z.write(p, str(Path(root.name) / p.relative_to(root)))
    spark.sparkContext.addPyFile(str(target))
    _SHIPPED.add(app)


def scratch_root(spark: SparkSession) -> str:
    """The shared folder named by spark.checkpoint.dir; one of our own only where that is unset and all is one machine."""
    named = spark.conf.get("spark.checkpoint.dir", None)
    if named:
        return named.rstrip("/")
    own = spark.sparkContext.getCheckpointDir()
    if own is None:
        if not (spark.sparkContext.master == "local" or spark.sparkContext.master.startswith("local[")):
            raise RuntimeError("set spark.checkpoint.dir to a folder that all executors share")
        own = "file://" + tempfile.mkdtemp(prefix="pullgraph-scratch-")
        spark.sparkContext.setCheckpointDir(own)
        own = spark.sparkContext.getCheckpointDir()
    return own.rstrip("/")


def materialize(df: DataFrame, name: str = "step", by: tuple[str, ...] = (), codec: str | None = None, file_rows: int | None = None) -> DataFrame:
    """Cut lineage by a compressed columnar table in the shared folder, in folders by the columns `by`.

    codec: zstd for rows of MB; readers hold whole pages of the session's own codec outside the heap until it is collected.
    file_rows: rows of a file at most, for rows of MB, as readers hold up to 4,096 rows of a file at a time.

    Unlike a block kept by one executor, the files outlive any executor, and they are several times smaller than the
    row format that checkpoint() writes.
    """
    spark = df.sparkSession
    path = f"{scratch_root(spark)}/{name}-{uuid.uuid4().hex}"
    out = df.write.option("compression", codec) if codec else df.write
    out = out.option("maxRecordsPerFile", file_rows) if file_rows else out
    out.partitionBy(*by).parquet(path) if by else out.parquet(path)
    out = spark.read.schema(df.schema).parquet(path)
    out._scratch_path = path
    for scope in _SCOPES.get()[-1:]:
        scope.append(out)
    return out


def scoped(fn: Callable[..., DataFrame]) -> Callable[..., DataFrame]:
    """A function that returns a table: its result is written, and then all tables made on the way are deleted.

    What is left on the shared disk is the result alone; the driver's garbage is collected, so that Spark drops the
    shuffle files of the jobs that are over.
    """

    @functools.wraps(fn)
    def run(*args, **kwargs) -> DataFrame:
        made: list[DataFrame] = []
        outer = _SCOPES.set((*_SCOPES.get(), made))
        try:
            plan = fn(*args, **kwargs)
            inner = _SCOPES.set((*_SCOPES.get(), []))
            try:
                out = materialize(plan, fn.__name__)
            finally:
                _SCOPES.reset(inner)
        finally:
            _SCOPES.reset(outer)
            for t in made:
                release(t)
        for scope in _SCOPES.get()[-1:]:
            scope.append(out)
        del plan
        collect_garbage(out.sparkSession)
        return out

    return run


def collect_garbage(spark: SparkSession) -> None:
    """Spark drops the shuffle files of a plan when the driver no longer refers to it; this lets it see that now."""
    gc.collect()
    spark.sparkContext._jvm.System.gc()


def release(df: DataFrame | None) -> None:
    """Delete the files of a materialize() result that nothing will read again."""
    path = getattr(df, "_scratch_path", None)
    if path is None:
        return
    jvm = df.sparkSession.sparkContext._jvm
    target = jvm.org.apache.hadoop.fs.Path(path)
    target.getFileSystem(df.sparkSession.sparkContext._jsc.hadoopConfiguration()).delete(target, True)
