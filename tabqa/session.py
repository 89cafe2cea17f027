"""Session helpers: table readers, shipping the package to executors, lineage cuts."""

from __future__ import annotations

import gc
import io
import os
import tempfile
import threading
import uuid
import zipfile
from collections.abc import Iterator
from contextlib import contextmanager
from pathlib import Path

from pyspark.sql import DataFrame, SparkSession

_SHIPPED = "tabqa.shipped"


def local_session(cores: int | str = "*", shuffle_partitions: int = 8, **conf: str) -> SparkSession:
    """A local session for tests and the bench; on a cluster the caller brings its own."""
    builder = (
        SparkSession.builder.master(f"local[{cores}]")
        .appName("tabqa")
        .config("spark.sql.shuffle.partitions", str(shuffle_partitions))
        .config("spark.sql.session.timeZone", "UTC")
        .config("spark.ui.enabled", "false")
        .config("spark.driver.memory", conf.pop("driver_memory", "12g"))
        .config("spark.sql.adaptive.enabled", "true")
    )
    for key, value in conf.items():
        builder = builder.config(key.replace("__", "."), value)
    spark = builder.getOrCreate()
    spark.sparkContext.setLogLevel("ERROR")
    return spark


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """One of the given tables; any path that Spark's readers can open."""
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def ship_package(spark: SparkSession) -> None:
    """Sends this package to the executors, once per application, through Spark's own file service."""
    sc = spark.sparkContext
    if getattr(sc, "_tabqa_shipped", False):
        return
    root = Path(__file__).resolve().parent
    packed = io.BytesIO()
    with zipfile.ZipFile(packed, "w", zipfile.ZIP_DEFLATED) as z:
        for path in sorted(root.rglob("*.py")):
            z.write(path, f"{root.name}/{path.relative_to(root)}")
    folder = tempfile.mkdtemp(prefix="tabqa-")
    target = os.path.join(folder, f"tabqa-{uuid.uuid4().hex[:12]}.zip")
    Path(target).write_bytes(packed.getvalue())
    sc.addPyFile(target)
    sc._tabqa_shipped = True


def shared_folder(spark: SparkSession) -> str:
    """The folder all executors share. Only where a local session names none (tests) is one made on this machine."""
    folder = spark.conf.get("spark.checkpoint.dir", None)
    if not folder:
        held = spark.sparkContext._jsc.sc().getCheckpointDir()
        if held.isDefined():
            return held.get()
        if not spark.sparkContext.master.startswith("local"):
            raise RuntimeError("a cluster needs spark.checkpoint.dir, a folder that the driver and all executors share")
        folder = "file://" + tempfile.mkdtemp(prefix="tabqa-shared-")
        spark.sparkContext.setCheckpointDir(folder)
    return folder


def cut(df: DataFrame) -> DataFrame:
    """Materialises a frame and cuts its lineage in the shared folder; survives lost executors."""
    spark = df.sparkSession
    if not spark.sparkContext._jsc.sc().getCheckpointDir().isDefined():
        spark.sparkContext.setCheckpointDir(shared_folder(spark))
    return df.checkpoint(eager=True)


def scratch_folder(spark: SparkSession) -> str:
    """Where this application's intermediate files lie: a folder of its own in the shared one."""
    return f"{shared_folder(spark)}/tabqa/{spark.sparkContext.applicationId}"


_SCRATCH = threading.local()


def written(df: DataFrame, name: str, compression: str = "snappy", keep: bool = False) -> DataFrame:
    """Writes a frame as Parquet in the shared folder and reads it back: smaller than a checkpoint."""
    spark = df.sparkSession
    path = f"{scratch_folder(spark)}/{name}-{uuid.uuid4().hex}"
    df.write.option("compression", compression).parquet(path)
    out = spark.read.parquet(path)
    out._tabqa_path = path
    if len(held := _SCRATCH.__dict__.setdefault("held", [])) > keep:
        held[-2 if keep else -1].append(out)
    return out


@contextmanager
def scratch() -> Iterator[None]:
    """Frames written inside are deleted at the end; those written with `keep` with the scratch around it, if there is one."""
    stack = _SCRATCH.__dict__.setdefault("held", [])
    stack.append([])
    try:
        yield
    finally:
        for df in stack.pop():
            discard(df)


def clean_up(spark: SparkSession) -> None:
    """Deletes all that this application wrote between steps; for its end, when no frame that was returned is needed any more."""
    _delete(spark, scratch_folder(spark))


def free_shuffles(spark: SparkSession) -> None:
    """Lets Spark's cleaner see which finished steps nothing refers to, so that their shuffle files go now and not at the driver's next collection."""
    gc.collect()
    spark._jvm.System.gc()


def discard(df: DataFrame) -> None:
    """Deletes the files of a written frame that nothing will read again."""
    _delete(df.sparkSession, df._tabqa_path)


def _delete(spark: SparkSession, folder: str) -> None:
    path = spark._jvm.org.apache.hadoop.fs.Path(folder)
    path.getFileSystem(spark._jsc.hadoopConfiguration()).delete(path, True)
