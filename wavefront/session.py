"""What every module needs to know of the session it is given: where to cut lineage and how wide to deal rows."""

from __future__ import annotations

import atexit
import contextlib
import shutil
import tempfile
from collections.abc import Iterator

from pyspark.sql import DataFrame, SparkSession


def shared_folder(spark: SparkSession) -> str:
    """The folder that all executors see: the one the cluster names. A local one is made only on a local master (tests)."""
    if found := spark.conf.get("spark.checkpoint.dir", None):
        return found.rstrip("/")
    if not spark.sparkContext.master.startswith("local[") and spark.sparkContext.master != "local":
        raise RuntimeError("spark.checkpoint.dir is not set: name a folder that all executors see")
    if "path" not in _made:
        _made["path"] = tempfile.mkdtemp(prefix="wavefront-")
        atexit.register(shutil.rmtree, _made["path"], ignore_errors=True)
    return _made["path"]


_made: dict[str, str] = {}


def ensure_checkpoint_dir(spark: SparkSession) -> None:
    if spark.sparkContext._jsc.sc().getCheckpointDir().isEmpty():
        spark.sparkContext.setCheckpointDir(shared_folder(spark))


def cut(df: DataFrame, laid_out: bool = False) -> DataFrame:
    """Materialise ``df`` in the shared checkpoint folder; the plan that follows starts from a leaf.

    A checkpoint inherits its plan's size estimate, and a join's estimate is the product of its sides: over the rounds
    of a loop it would grow to numbers of millions of digits. So the leaf is made anew without it. With ``laid_out`` the
    leaf keeps what is known of its partitioning, so rounds that join on one key need no exchange of it; without, joins
    get fresh exchanges, whose hot partitions adaptive execution may split. Shuffle files behind the leaf go at once: nothing
    reads them again, and over many short stages they would stay until the driver collects its garbage.
    """
    spark = df.sparkSession
    ensure_checkpoint_dir(spark)
    with conf(spark, spark__sql__classic__shuffleDependency__fileCleanup__enabled="true"):
        kept = df.select("*").checkpoint(eager=True)._jdf  # a plan of its own takes the option
    session = kept.sparkSession()
    file = kept.queryExecution().analyzed().rdd().getCheckpointFile()
    if not laid_out:
        return _named(DataFrame(session.internalCreateDataFrame(kept.queryExecution().toRdd(), kept.schema(), False), spark), file)
    leaf, none = kept.queryExecution().analyzed(), spark._jvm.scala.Option.empty()
    plain = leaf.copy(leaf.output(), leaf.rdd(), leaf.outputPartitioning(), leaf.outputOrdering(), False, none, session, none, none)
    return _named(DataFrame(spark._jvm.org.apache.spark.sql.classic.Dataset.ofRows(session, plain), spark), file)


def _named(df: DataFrame, file) -> DataFrame:
    df.checkpoint_file = file.get() if file.isDefined() else None  # type: ignore[attr-defined]
    return df


def let_go(df: DataFrame) -> None:
    """Delete the files behind a leaf that ``cut`` has made and nothing will read again: a loop's last state but one."""
    if file := getattr(df, "checkpoint_file", None):
        path = df.sparkSession._jvm.org.apache.hadoop.fs.Path(file)
        path.getFileSystem(df.sparkSession.sparkContext._jsc.hadoopConfiguration()).delete(path, True)


def shuffle_width(spark: SparkSession) -> int:
    return int(spark.conf.get("spark.sql.shuffle.partitions", "200"))


@contextlib.contextmanager
def conf(spark: SparkSession, **settings: str) -> Iterator[None]:
    """Set runtime SQL options (dots written as double underscores) and put the old values back."""
    names = {k: k.replace("__", ".") for k in settings}
    old = {k: spark.conf.get(n, None) for k, n in names.items()}
    try:
        for k, n in names.items():
            spark.conf.set(n, settings[k])
        yield
    finally:
        for k, n in names.items():
            spark.conf.unset(n) if old[k] is None else spark.conf.set(n, old[k])
