"""What the corpus operators share: reading, the shared folder, folds, worker-side caches."""

from __future__ import annotations

import atexit
import gc
import sys
import tempfile
import uuid

from py4j.protocol import Py4JJavaError
from pyspark import cloudpickle
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: A word of every operator here: a run of anything but the six ASCII white-space characters.
WORD = r"[^\x20\x09-\x0D]+"


def travels(name: str) -> None:
    """Ship the functions of module ``name`` with their code, so that executors need no copy of this package."""
    cloudpickle.register_pickle_by_value(sys.modules[name])


travels(__name__)


#: Rows of a batch between Spark and Python: texts are long, and a batch lies in memory on both sides.
BATCH_ROWS = "2000"


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", BATCH_ROWS)
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def remainder(doc_id: str | Column, modulus: int) -> Column:
    """crc32 of the id's decimal text modulo ``modulus``; a null id counts as the empty text."""
    col = F.col(doc_id) if isinstance(doc_id, str) else doc_id
    return F.pmod(F.crc32(F.coalesce(col.cast("string"), F.lit("")).cast("binary")), F.lit(modulus))


def fresh(df: DataFrame, *names: str) -> list[str]:
    """These names, with underscores before them until ``df`` has no such column."""
    taken, out = {c.lower() for c in df.columns}, []
    for name in names:
        while name.lower() in taken:
            name = f"_{name}"
        taken.add(name.lower())
        out.append(name)
    return out


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share: spark.checkpoint.dir, or in a test session a temporary one."""
    named = spark.conf.get("spark.checkpoint.dir", None)
    if named:
        return named.rstrip("/")
    sc = spark.sparkContext
    current = sc._jsc.sc().getCheckpointDir()
    if current.isEmpty():
        if not sc.master.startswith("local"):
            raise RuntimeError("set spark.checkpoint.dir to a folder that all executors share")
        sc.setCheckpointDir(tempfile.mkdtemp(prefix="calseries-"))
        current = sc._jsc.sc().getCheckpointDir()
    return current.get().rstrip("/")


def staged(df: DataFrame, label: str, *by: str) -> DataFrame:
    """Write ``df`` to the shared folder as Parquet, in folders by the columns ``by``, and read it back: its lineage
    ends there. The folder goes when the driver's Python ends."""
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/calseries-{label}-{uuid.uuid4().hex}"
    (df.write.partitionBy(*by) if by else df.write).parquet(path)
    trim(spark)
    atexit.register(_remove, spark, path)
    out = spark.read.schema(df.schema).parquet(path)
    out.staged_at = path
    return out


def forget(staged_: DataFrame, part: str = "") -> None:
    """Remove what ``staged`` wrote, or one folder of it, once nothing reads it any more."""
    _remove(staged_.sparkSession, f"{staged_.staged_at}/{part}" if part else staged_.staged_at)


def release(spark: SparkSession) -> None:
    """Let Spark remove the shuffle files behind what is staged by now: it does so once the driver drops its handles."""
    gc.collect()
    spark.sparkContext._jvm.System.gc()


def trim(spark: SparkSession) -> None:
    """Have the driver's JVM hand freed native memory back to the system.

    Planning many queries and compiling them leaves the allocator with freed pieces, some hundred MB beside the heap,
    which stand in the way when the compiler next needs much at once. A JVM without this command keeps them."""
    jvm, make = spark.sparkContext._jvm, spark.sparkContext._gateway.new_array
    name, given, kinds = "javax.management.ObjectName", make(jvm.java.lang.Object, 4), make(jvm.java.lang.Class, 4)
    for i, kind in enumerate((name, "java.lang.String", "[Ljava.lang.Object;", "[Ljava.lang.String;")):
        kinds[i] = jvm.java.lang.Class.forName(kind)
    try:
        given[0], given[1] = jvm.javax.management.ObjectName("com.sun.management:type=DiagnosticCommand"), "systemTrimNativeHeap"
        # the server's own class is closed to callers, its interface isn't
        invoke = jvm.java.lang.Class.forName("javax.management.MBeanServer").getMethod("invoke", kinds)
        invoke.invoke(jvm.java.lang.management.ManagementFactory.getPlatformMBeanServer(), given)
    except Py4JJavaError:
        pass


def _remove(spark: SparkSession, path: str) -> None:
    sc = spark.sparkContext
    if sc._jsc is None:
        return
    target = sc._jvm.org.apache.hadoop.fs.Path(path)
    target.getFileSystem(sc._jsc.hadoopConfiguration()).delete(target, True)


def stash(key: str, make):
    """A value made once in each Python process, which serves the tasks of one worker in turn."""
    kept = sys.modules.setdefault("_calseries_stash", type(sys)("_calseries_stash"))
    if not hasattr(kept, key):
        setattr(kept, key, make())
    return getattr(kept, key)


def in_share(hashed: Column, rows: int, total: int) -> Column:
    """Whether a row with this 64-bit hash is one of about ``rows`` of ``total``, however large the total is."""
    if rows >= total:
        return F.lit(True)
    return hashed < F.lit((rows << 64) // total - (1 << 63))


def labelled_sample(docs: DataFrame, labels: DataFrame, label: str, modulus: int, left_out: int, rows: int) -> DataFrame:
    """(doc_id, text, y) of at most about ``rows`` labelled documents outside the held-out fold.

    The share that is kept follows from the number of labelled rows, and a hash of the id says which ones, so reruns
    agree. Documents without a label, an id or with a label other than 0 or 1 are left out. A document that is
    labelled twice counts with its larger label."""
    trim(docs.sparkSession)
    marks = (
        labels.select(F.col("doc_id"), F.col(label).cast("int").alias("y"))
        .where(F.col("y").isin(0, 1) & F.col("doc_id").isNotNull() & (remainder("doc_id", modulus) != left_out))
        .groupBy("doc_id").agg(F.max("y").alias("y"))
    )
    marks = marks.where(in_share(F.xxhash64("doc_id"), rows, marks.count()))
    return docs.select("doc_id", "text").join(F.broadcast(marks), "doc_id")  # about ``rows`` ids at most
