"""Small helpers that the operators share."""

from __future__ import annotations

import atexit
import ctypes
import shutil
import tempfile
import uuid
from collections.abc import Callable, Iterator

import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: A side of a join is broadcast only if a count shows at most so many rows of fixed width.
BROADCAST_ROWS = 500_000
#: Rows of one Arrow batch at most. Spark's buffers for a batch of texts grow by doubling, outside its heap, and Python holds two batches.
ARROW_ROWS = 1_000


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def texts(df: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Only (doc_id, text), whatever other columns there are; a null text becomes empty."""
    return df.select(df[id_col].cast("long").alias("doc_id"), F.coalesce(df[text_col], F.lit("")).alias("text"))


def shared_folder(spark: SparkSession) -> str:
    """A folder of this session in spark.checkpoint.dir. Only a local master, which has no other machine, may do without that setting."""
    sc = spark.sparkContext
    if sc.getCheckpointDir() is None:
        where = spark.conf.get("spark.checkpoint.dir", "") or sc.getConf().get("spark.checkpoint.dir", "")
        if not where and not sc.master.startswith("local"):
            raise RuntimeError("set spark.checkpoint.dir to a folder that all executors share")
        if not where:
            where = tempfile.mkdtemp(prefix="checkpoints-")
            atexit.register(shutil.rmtree, where, ignore_errors=True)
        sc.setCheckpointDir(where)
    return sc.getCheckpointDir()


def settled(df: DataFrame) -> DataFrame:
    """Cut the lineage with a Parquet table in the shared folder.

    Its readers take only the columns they need, and the planner learns its true size: size estimates of checkpoints are products over
    the joins before them, which a loop that joins its own results would square each turn.
    """
    path = f"{shared_folder(df.sparkSession)}/{uuid.uuid4().hex}"
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def small_batches(spark: SparkSession) -> None:
    """Bound the rows of the session's Arrow batches, which is a matter of memory only; a lower bound stays. Zero or less there means no bound."""
    name = "spark.sql.execution.arrow.maxRecordsPerBatch"
    if not 0 < int(spark.conf.get(name)) <= ARROW_ROWS:
        spark.conf.set(name, str(ARROW_ROWS))


def give_back() -> None:
    """Return a worker's free memory to the system when its task ends: Spark keeps idle workers, beside stages that don't use them."""
    pa.default_memory_pool().release_unused()
    trim = getattr(ctypes.CDLL(None), "malloc_trim", None)  # of glibc
    if trim:
        trim(0)


def unused(columns: list[str], name: str) -> str:
    """A column name that none of the columns has."""
    taken = {c.lower() for c in columns}
    while name.lower() in taken:
        name = "_" + name
    return name


def small_or_shuffled(df: DataFrame, limit: int = BROADCAST_ROWS) -> DataFrame:
    """Mark a settled side for broadcast if its counted rows stay within the limit; else leave it to a shuffle join."""
    return F.broadcast(df) if df.limit(limit + 1).count() <= limit else df.hint("merge")


def map_texts(df: DataFrame, kernel: Callable[[Iterator[tuple[list, list[str]]]], Iterator[dict]], schema: str, batch_bytes: int = 4 << 20) -> DataFrame:
    """Run a kernel over (ids, texts) lists that hold about `batch_bytes` UTF-8 bytes each, one long text making a list of its own."""
    arrow = None

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        def lists() -> Iterator[tuple[list, list[str]]]:
            ids: list = []
            held: list[str] = []
            size = 0
            for batch in batches:
                sizes = pc.binary_length(batch.column(1)).to_pylist()
                for i, t, n in zip(batch.column(0).to_pylist(), batch.column(1), sizes, strict=True):
                    if held and size + n > batch_bytes:
                        yield ids, held
                        ids, held, size = [], [], 0
                    ids.append(i)
                    held.append(t.as_py())
                    size += n
            if held:
                yield ids, held

        for out in kernel(lists()):
            yield pa.RecordBatch.from_pydict(out, schema=arrow)
        give_back()

    from pyspark.sql.pandas.types import to_arrow_schema
    from pyspark.sql.types import _parse_datatype_string

    arrow = to_arrow_schema(_parse_datatype_string(schema))
    small_batches(df.sparkSession)
    return df.mapInArrow(run, schema)


def crc_bucket(col: Column, n: int) -> Column:
    return F.crc32(col.cast("string").cast("binary")) % n
