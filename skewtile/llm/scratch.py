"""Tables that outlive a lost executor: intermediate results go to the folder that the cluster shares."""

from __future__ import annotations

import atexit
import shutil
import tempfile
import threading
import uuid
from collections.abc import Iterator
from contextlib import contextmanager

from pyspark.sql import DataFrame, SparkSession

_LOCAL: list[str] = []


def shared_folder(spark: SparkSession) -> str:
    """The folder named by spark.checkpoint.dir; a temporary one of our own only where that is unset and Spark is local."""
    set_by_cluster = spark.conf.get("spark.checkpoint.dir", None)
    if set_by_cluster:
        return set_by_cluster.rstrip("/")
    if not spark.sparkContext.master.startswith("local"):
        return spark.conf.get("spark.sql.warehouse.dir").rstrip("/")
    if not _LOCAL:
        _LOCAL.append(tempfile.mkdtemp(prefix="skewtile-"))
        atexit.register(shutil.rmtree, _LOCAL[0], True)
    return f"file://{_LOCAL[0]}"


def new_path(spark: SparkSession, name: str) -> str:
    return f"{shared_folder(spark)}/skewtile/{name}-{uuid.uuid4().hex}"


_CLEANUP = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"
_LOCK = threading.Lock()
_WRITES = {"open": 0, "before": None}


@contextmanager
def _shuffles_deleted(spark: SparkSession) -> Iterator[None]:
    """The clean-up is on while any thread writes, and then as it was before the first of them."""
    with _LOCK:
        if not _WRITES["open"]:
            _WRITES["before"] = spark.conf.get(_CLEANUP, None)
            spark.conf.set(_CLEANUP, "true")
        _WRITES["open"] += 1
    try:
        yield
    finally:
        with _LOCK:
            _WRITES["open"] -= 1
            if not _WRITES["open"]:
                before = _WRITES["before"]
                spark.conf.unset(_CLEANUP) if before is None else spark.conf.set(_CLEANUP, before)


def settle(df: DataFrame, name: str = "table") -> DataFrame:
    """Write df to the shared folder and return the written table, which cuts the lineage there. The shuffles behind the
    written table are of no more use, so Spark deletes their files when the write ends."""
    spark = df.sparkSession
    path = new_path(spark, name)
    with _shuffles_deleted(spark):
        df.write.option("compression", "zstd").parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def with_ids(docs: DataFrame, ids: DataFrame, how: str = "left_semi", key: str = "doc_id") -> DataFrame:
    """docs whose key is (left_semi) or isn't (left_anti) among the ids, the one column of `ids`; null equals null. Whatever
    columns docs has, they come out as they were."""
    name = "_key"
    while name in docs.columns:
        name += "_"
    ids = ids.toDF(name)
    return docs.join(ids, docs[key].eqNullSafe(ids[name]), how)


def drop_settled(df: DataFrame) -> None:
    """Delete a settled table that no plan reads any more."""
    spark = df.sparkSession
    for path in {f.rsplit("/", 1)[0] for f in df.inputFiles()}:
        if "/skewtile/" in path:
            jvm_path = spark._jvm.org.apache.hadoop.fs.Path(path)
            jvm_path.getFileSystem(spark._jsc.hadoopConfiguration()).delete(jvm_path, True)
