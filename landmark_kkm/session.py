"""Session helpers: code shipping, the shared folder, lineage cuts and parallel scans."""

from __future__ import annotations

import atexit
import os
import re
import shutil
import tempfile
import uuid
import zipfile
from pathlib import Path

from pyspark import Broadcast, StorageLevel
from pyspark.sql import DataFrame, SparkSession

#: Partitions for each core, from which forced() leaves them as they are.
ROUNDS = 4

_SHIPPED: set[str] = set()
_MADE: list[str] = []
_HELD: list[Broadcast | DataFrame] = []


def local_session(cores: int | str = 8, shuffle_partitions: int = 8, **conf: str) -> SparkSession:
    """A local session with the settings that tests and the bench use. Each Python worker has one thread, as there is one for each core."""
    os.environ.setdefault("OMP_NUM_THREADS", "1")
    builder = (
        SparkSession.builder.master(f"local[{cores}]")
        .config("spark.sql.shuffle.partitions", str(shuffle_partitions))
        .config("spark.sql.session.timeZone", "UTC")
        .config("spark.ui.enabled", "false")
        .config("spark.driver.memory", "8g")
        .config("spark.sql.execution.arrow.pyspark.enabled", "true")
        .config("spark.driver.host", "127.0.0.1")
    )
    for key, value in conf.items():
        builder = builder.config(key.replace("__", "."), value)
    return builder.getOrCreate()


def ship(spark: SparkSession) -> None:
    """Send this package to the executors once per application, so that workers can import it."""
    app = spark.sparkContext.applicationId
    if app in _SHIPPED:
        return
    root = Path(__file__).resolve().parent
    path = os.path.join(tempfile.mkdtemp(prefix="pkg"), f"{root.name}.zip")
    with zipfile.ZipFile(path, "w") as z:
        for f in sorted(root.rglob("*.py")):
            z.write(f, f.relative_to(root.parent))
    spark.sparkContext.addPyFile(path)
    _SHIPPED.add(app)


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share: spark.checkpoint.dir, or the checkpoint folder that was set. A local session without either gets one that goes with the process."""
    base = spark.conf.get("spark.checkpoint.dir", None)
    if not base:
        context = spark.sparkContext._jsc.sc()
        if not context.getCheckpointDir().isDefined():
            if not spark.sparkContext.master.startswith("local"):
                raise RuntimeError("set spark.checkpoint.dir to a folder that driver and executors share")
            own = tempfile.mkdtemp(prefix="checkpoint")
            atexit.register(shutil.rmtree, own, ignore_errors=True)
            spark.sparkContext.setCheckpointDir(own)
        base = context.getCheckpointDir().get()
    return base.rstrip("/")


def new_path(spark: SparkSession, what: str) -> str:
    path = f"{shared_dir(spark)}/{what}-{uuid.uuid4().hex}"
    _MADE.append(path)
    return path


def clean_up(spark: SparkSession) -> int:
    """Delete what this process wrote to the shared folder, once no DataFrame that reads it is needed any more; the number of folders."""
    count = 0
    while _MADE:
        path = spark._jvm.org.apache.hadoop.fs.Path(_MADE.pop())
        count += bool(path.getFileSystem(spark._jsc.hadoopConfiguration()).delete(path, True))
    return count


def hold(spark: SparkSession, value) -> Broadcast:
    """A broadcast that release() can give back: its files lie on the driver and on each executor until then."""
    _HELD.append(spark.sparkContext.broadcast(value))
    return _HELD[-1]


def keep(df: DataFrame) -> DataFrame:
    """df, persisted and evaluated over all cores, until release() gives it back."""
    _HELD.append(forced(df))
    return _HELD[-1]


def held() -> int:
    """How many broadcasts and kept DataFrames are held, for release()."""
    return len(_HELD)


def release(since: int = 0) -> None:
    """Destroy the broadcasts held since then, and unpersist what was kept, once no DataFrame that was made with them is evaluated any more."""
    while len(_HELD) > since:
        one = _HELD.pop()
        one.destroy() if isinstance(one, Broadcast) else one.unpersist()


def materialize(df: DataFrame, what: str = "step") -> DataFrame:
    """Cut the lineage: write to the shared folder as Parquet and read again (survives lost executors)."""
    path = new_path(df.sparkSession, what)
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def splits(df: DataFrame) -> int:
    """The partitions of df, without running anything: where a shuffle makes them, as many as shuffles have."""
    plan = df._jdf.queryExecution().executedPlan().toString().split("InMemoryRelation")[0]  # what is cached has its partitions
    if re.search(r"Exchange (hash|range|single|RoundRobin|SinglePartition)", plan):
        return int(df.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    return df.rdd.getNumPartitions()


def spread(df: DataFrame) -> DataFrame:
    """Deal a scan of few splits over all cores; larger scans stay as they are."""
    wanted = df.sparkSession.sparkContext.defaultParallelism
    return df.repartition(wanted) if splits(df) < wanted else df


def forced(df: DataFrame) -> DataFrame:
    """df, persisted and evaluated, over all cores: what adaptive execution has packed into fewer partitions is dealt anew, as each iteration runs on them.

    So is what has a few more than the cores, as the cores would wait for the last ones in each iteration; from ROUNDS partitions a core this is little."""
    df = df.persist(StorageLevel.MEMORY_AND_DISK)
    df.write.format("noop").mode("overwrite").save()
    wanted = df.sparkSession.sparkContext.defaultParallelism
    found = df.rdd.getNumPartitions()
    if found >= ROUNDS * wanted or found and found % wanted == 0:
        return df
    dealt = df.repartition(max(1, found // wanted) * wanted).persist(StorageLevel.MEMORY_AND_DISK)
    dealt.write.format("noop").mode("overwrite").save()
    df.unpersist()
    return dealt


def read_table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")
