"""Where operators keep intermediate tables.

Intermediate tables are Parquet in the folder that the session names in
``spark.checkpoint.dir``, which driver and executors share, so a lost executor
costs no more than the tasks it was running.
"""

from __future__ import annotations

import re
import tempfile
import threading
import uuid
from contextlib import contextmanager
from contextvars import ContextVar

from py4j.protocol import Py4JError
from pyspark.errors import AnalysisException
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

CLEANUP = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"
ARROW = "spark.sql.execution.arrow.maxBytesPerBatch"
ARROW_BYTES = 4 << 20  # a batch between JVM and Python; whole ones lie in both, in buffers that grow by doubling
_lock, _writers = threading.Lock(), {"n": 0, "before": {}}


def shared_root(spark: SparkSession) -> str:
    """The session's shared folder; a temporary one is made only in local mode, where all tasks run on this machine."""
    named = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getConf().get("spark.checkpoint.dir")
    if named:
        return named.rstrip("/")
    held = spark.sparkContext.getCheckpointDir()
    if not held:
        if not spark.sparkContext.master.startswith("local"):
            raise ValueError("set spark.checkpoint.dir to a folder that driver and executors share")
        spark.sparkContext.setCheckpointDir("file://" + tempfile.mkdtemp(prefix="gridtide-"))
        held = spark.sparkContext.getCheckpointDir()
    return held.rstrip("/")


def _byte_count(said: str) -> int:
    """Bytes that a setting of Spark names, as 64m, 67108864b or 1000."""
    number, unit = re.fullmatch(r"\s*(-?\d+)\s*([a-z]?)[a-z]*\s*", said.lower()).groups()
    return int(number) << 10 * " kmgtp".index(unit if unit in "kmgtp" and unit else " ")


class _Writing:
    """Shuffle clean-up is on and Arrow batches are small while any write of this module runs, and as before once the last has ended."""

    def __init__(self, spark: SparkSession):
        self.conf = spark.conf

    def __enter__(self):
        with _lock:
            if not _writers["n"]:
                most = self.conf.get(ARROW, None)
                wanted = {CLEANUP: "true"}
                if most is None or not 0 < _byte_count(most) <= ARROW_BYTES:
                    wanted[ARROW] = str(ARROW_BYTES)
                _writers["before"] = {k: self.conf.get(k, None) for k in wanted}
                for k, v in wanted.items():
                    self.conf.set(k, v)
            _writers["n"] += 1

    def __exit__(self, *_):
        with _lock:
            _writers["n"] -= 1
            if not _writers["n"]:
                for k, v in _writers["before"].items():
                    if v is None:
                        self.conf.unset(k)
                    else:
                        self.conf.set(k, v)


_made: ContextVar[list | None] = ContextVar("made", default=None)


@contextmanager
def scratches():
    """Deletes at its end every Scratch that was made inside, once nothing reads them any more."""
    held: list[Scratch] = []
    token = _made.set(held)
    try:
        yield
    finally:
        _made.reset(token)
        for one in held:
            one.close()


def trim_native(spark: SparkSession) -> str:
    """Give memory that the driver's JVM has freed outside its heap back to the system; returns what the JVM says of it.

    Each query leaves some of it with the C library, in an arena of one of the
    driver's many threads, so a long run of small queries grows beyond the heap.
    A JVM without that command keeps its memory, and nothing is said.
    """
    jvm, gateway = spark.sparkContext._jvm, spark.sparkContext._gateway

    def array(kind, *values):
        made = gateway.new_array(kind, len(values))
        for i, value in enumerate(values):
            made[i] = value
        return made

    try:
        kind, beans = jvm.java.lang.Class, "javax.management"
        takes = array(kind, *(kind.forName(k) for k in (f"{beans}.ObjectName", "java.lang.String", "[Ljava.lang.Object;", "[Ljava.lang.String;")))
        call = kind.forName(f"{beans}.MBeanServer").getMethod("invoke", takes)
        commands = jvm.javax.management.ObjectName("com.sun.management:type=DiagnosticCommand")
        said = call.invoke(jvm.java.lang.management.ManagementFactory.getPlatformMBeanServer(), array(jvm.java.lang.Object, commands, "systemTrimNativeHeap", None, None))
    except Py4JError:
        return ""
    return str(said)


class Scratch:
    """A private folder of intermediate tables below the shared root."""

    def __init__(self, spark: SparkSession, purpose: str):
        self.spark = spark
        if (held := _made.get()) is not None:
            held.append(self)
        self.path = f"{shared_root(spark)}/gridtide/{purpose}-{uuid.uuid4().hex}"

    def keep(self, frame: DataFrame, name: str) -> DataFrame:
        """Write ``frame`` and read it back, which cuts its lineage.

        The written table replaces the frame, so its shuffle files go as soon
        as the write has ended instead of when the driver next collects garbage.
        Texts, sets and signatures reach Python in batches of ARROW_BYTES.
        """
        where = f"{self.path}/{name}"
        with _Writing(self.spark):
            frame.write.mode("overwrite").parquet(where)
        return self.spark.read.schema(frame.schema).parquet(where)

    def read(self, name: str, schema) -> DataFrame:
        return self.spark.read.schema(schema).parquet(f"{self.path}/{name}")

    def drop(self, *names: str) -> None:
        """Delete tables that no later plan reads."""
        jvm, conf = self.spark.sparkContext._jvm, self.spark.sparkContext._jsc.hadoopConfiguration()
        for name in names:
            path = jvm.org.apache.hadoop.fs.Path(f"{self.path}/{name}" if name else self.path)
            path.getFileSystem(conf).delete(path, True)
        trim_native(self.spark)

    def close(self) -> None:
        """Delete the folder; results that still read it are lost."""
        self.drop("")


BROADCAST_ROWS = 1 << 19  # rows of a few numbers that are broadcast at most


def bounded(frame: DataFrame, rows: int = BROADCAST_ROWS) -> DataFrame:
    """``frame`` (a written table) marked for broadcast where it has few enough rows, else as it is."""
    return F.broadcast(frame) if frame.count() <= rows else frame


def partitions(spark: SparkSession) -> int:
    """The session's shuffle partition count, the scale setting operators follow."""
    return int(spark.conf.get("spark.sql.shuffle.partitions"))


def free_name(columns, wanted: str) -> str:
    """``wanted``, or with underscores before it where a column already has that name (case ignored, as Spark does)."""
    taken = {c.lower() for c in columns}
    while wanted.lower() in taken:
        wanted = "_" + wanted
    return wanted


def with_row_ids(documents: DataFrame, name: str, scratch: Scratch) -> DataFrame:
    """``documents`` with a long column ``name`` that tells every row from all others, repeated rows too.

    The id is the row's file number and place in that file, so it comes out
    the same in every plan that reads these documents again.  Documents that no
    file holds are written first.
    """

    def place(frame: DataFrame) -> tuple[Column, Column]:
        meta = frame.metadataColumn("_metadata")
        found = meta["file_path"], meta["row_index"]
        frame.select(found[0].alias("a"), found[1].alias("b")).schema  # noqa: B018 - resolves the columns
        return found

    try:
        path, row = place(documents)
    except AnalysisException:
        documents = scratch.keep(documents, "placed-rows")
        path, row = place(documents)
    held = free_name([*documents.columns, name], "file")
    at = free_name([*documents.columns, name, held], "row")
    number = free_name([*documents.columns, name, held, at], "number")
    files = documents.select(path.alias(held)).distinct()
    files = scratch.keep(files.select(held, F.row_number().over(Window.partitionBy(F.lit(0)).orderBy(held)).cast("long").alias(number)), "placed-files")  # a row for each file
    rows = documents.select("*", path.alias(held), row.alias(at)).join(bounded(files, 1 << 16), held)
    return rows.withColumn(name, F.shiftleft(F.col(number), 40) + F.col(at)).drop(held, at, number)
