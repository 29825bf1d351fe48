"""Helpers shared by the text operators of this subpackage.

Conventions that every operator here follows:

* rows are never dropped, capped or sampled unless dropping is the operator's decision;
* a null text counts as the empty text;
* a column of the input that bears the name of an output column is replaced by it.
"""

from __future__ import annotations

import ctypes
import gc
import os
import tempfile
import uuid
import zipfile
from collections.abc import Callable, Iterator, Sequence
from functools import cache, partial
from pathlib import Path

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, functions as F, types as T
from pyspark.sql.pandas.types import to_arrow_type

_shipped: set[str] = set()
#: Rows of an Arrow batch at most: texts are long, and a worker holds two batches besides its own tables.
BATCH_ROWS = 2000


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def ship(spark: SparkSession) -> None:
    """Make this package importable in the Python workers, once per application."""
    if int(spark.conf.get("spark.sql.execution.arrow.maxRecordsPerBatch")) > BATCH_ROWS:
        spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", BATCH_ROWS)
    app = spark.sparkContext.applicationId
    if app in _shipped:
        return
    root = Path(__file__).resolve().parents[1]
    target = os.path.join(tempfile.mkdtemp(), f"{root.name}_src.zip")
    with zipfile.ZipFile(target, "w", zipfile.ZIP_DEFLATED) as z:
        for p in sorted(root.rglob("*.py")):
            z.write(p, p.relative_to(root.parent))
    spark.sparkContext.addPyFile(target)
    _shipped.add(app)


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share; one of our own only where none is set and all run on one machine."""
    sc = spark.sparkContext
    where = spark.conf.get("spark.checkpoint.dir", None)
    if not where:
        kept = sc._jsc.sc().getCheckpointDir()
        if not kept.isDefined() and not sc.master.startswith("local["):
            raise RuntimeError("set spark.checkpoint.dir to a folder that driver and executors share")
        where = kept.get() if kept.isDefined() else tempfile.mkdtemp(prefix="shared")
    if not sc._jsc.sc().getCheckpointDir().isDefined():
        sc.setCheckpointDir(where)
    return where


def fresh_path(spark: SparkSession, name: str) -> str:
    """A new folder name in the shared folder; what is written there goes when the application ends."""
    where = f"{shared_dir(spark).rstrip('/')}/{name}-{uuid.uuid4().hex}"
    path = spark._jvm.org.apache.hadoop.fs.Path(where)
    fs = path.getFileSystem(spark._jsc.hadoopConfiguration())
    fs.mkdirs(path.getParent())
    fs.deleteOnExit(path)
    return where


def cut(df: DataFrame) -> DataFrame:
    """Compute ``df`` once into the shared folder and cut its lineage there."""
    shared_dir(df.sparkSession)
    return df.checkpoint(eager=True)


def tidy(spark: SparkSession) -> None:
    """Let Spark remove shuffle files and checkpoints that nothing refers to any more.

    The cleaner acts when the driver collects its garbage, which a driver with little to do puts off
    while the executors' disks fill; call it between the phases of a long operator.
    """
    gc.collect()
    pa.default_memory_pool().release_unused()
    spark.sparkContext._jvm.System.gc()


def may_hold(rows: DataFrame, key: str, chosen: DataFrame, bits: int = 23) -> DataFrame:
    """Append ``__hit``: false only where ``key`` is certainly not a key of ``chosen``.

    The hashes of the chosen keys are a bitmap of ``2**bits`` bits, of which at most one row for each
    32,768 bits is broadcast (1 MB for 23 bits, whatever the input), so rows that a join could not
    meet need not be shuffled.
    """
    place = (F.pmod(F.xxhash64(key), F.lit(1 << bits)) + 1).alias("__place")
    maps = chosen.select(place).groupBy(F.bitmap_bucket_number("__place").alias("__bucket")).agg(F.bitmap_construct_agg(F.bitmap_bit_position("__place")).alias("__map"))
    placed = rows.withColumn("__place", place).withColumn("__bucket", F.bitmap_bucket_number("__place"))
    at = F.bitmap_bit_position("__place")
    byte = F.conv(F.hex(F.substring(F.col("__map"), (F.floor(at / 8) + 1).cast("int"), F.lit(1))), 16, 10).cast("int")
    hit = F.getbit(byte, (at % 8).cast("int")) == 1
    return placed.join(F.broadcast(maps), "__bucket", "left").withColumn("__hit", F.coalesce(hit, F.lit(False))).drop("__bucket", "__place", "__map")


def draw(df: DataFrame, key: str, max_rows: int) -> DataFrame:
    """At most ``max_rows`` rows, those whose key hashes lowest.

    A cut on the hash, set from the number of rows, lets about three times as many through, so what
    the tasks sort and send does not grow with their number.
    """
    rows = df.count()
    low = F.pmod(F.xxhash64(key), F.lit(1 << 40))
    near = df if rows <= 3 * max_rows else df.where(low < int((1 << 40) * 3 * max_rows / rows))
    return near.orderBy(low, key).limit(max_rows)


#: What frees the memos that operators keep in a worker, and the operator whose memos are held.
_memos: list[Callable[[], None]] = []
_owner: list[str] = [""]


def trim() -> None:
    """Give what this process has freed back to the machine."""
    pa.default_memory_pool().release_unused()
    try:
        ctypes.CDLL(None).malloc_trim(0)
    except (AttributeError, OSError):  # another C library
        pass


@cache
def keep_freed(most: int = 32 << 20) -> None:
    """Have this process use freed arrays again.  The C library otherwise gives each array of over
    128 kB back to the machine, and every new one costs page faults; ``trim`` still frees."""
    try:
        c = ctypes.CDLL(None)
        c.mallopt(-3, most)  # M_MMAP_THRESHOLD
        c.mallopt(-1, 2 * most)  # M_TRIM_THRESHOLD
    except (AttributeError, OSError):  # another C library
        pass


def keeps_memo(drop: Callable[[], None]) -> None:
    """Have ``drop`` called in a worker when another operator begins there."""
    _memos.append(drop)


def begin(owner: str) -> None:
    """A task of ``owner`` begins: workers are used again, and memos of other operators go."""
    if _owner[0] == owner:
        return
    if _owner[0]:
        for drop in _memos:
            drop()
        gc.collect()
        trim()
    _owner[0] = owner


def tidied(batches: Iterator[pa.RecordBatch], run: Callable) -> Iterator[pa.RecordBatch]:
    """``run`` over the batches of a task: memos of other operators go before it, freed memory after it."""
    begin(getattr(run, "func", run).__module__)
    yield from run(batches)
    trim()


def _run(batches: Iterator[pa.RecordBatch], fn: Callable, n_keep: int, text_at: int, kinds: list[pa.DataType], names: list[str]) -> Iterator[pa.RecordBatch]:
    begin(getattr(fn, "func", fn).__module__)
    for b in batches:
        made = fn([x if x is not None else "" for x in b.column(text_at).to_pylist()])
        arrays = list(b.columns[:n_keep]) + [pa.array(c, type=k) if not isinstance(c, pa.Array) else c for c, k in zip(made, kinds, strict=True)]
        yield pa.RecordBatch.from_arrays(arrays, names=names)
        del made, arrays
    trim()


def with_text_columns(df: DataFrame, text_col: str, fn: Callable[[list[str]], Sequence], fields: Sequence[tuple[str, T.DataType]], keep: Sequence[str] | None = None) -> DataFrame:
    """Append columns that ``fn`` computes from the texts of one Arrow batch.

    ``fn`` takes a list of strings (nulls already empty) and returns one list per field.
    ``keep`` names the input columns that stay (all by default); narrow, no shuffle.
    """
    ship(df.sparkSession)
    new = [n for n, _ in fields]
    kept = [c for c in (df.columns if keep is None else keep) if c.lower() not in {n.lower() for n in new}]
    rows = df.select(*[df[f"`{c}`"] for c in kept], df[f"`{text_col}`"].cast("string").alias("__text"))
    schema = T.StructType([*rows.schema.fields[:-1], *(T.StructField(n, k) for n, k in fields)])
    run = partial(_run, fn=fn, n_keep=len(kept), text_at=len(kept), kinds=[to_arrow_type(k) for _, k in fields], names=kept + new)
    return rows.mapInArrow(run, schema)
