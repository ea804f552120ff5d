"""Shared helpers: tables on the shared folder, Arrow passes over whole texts."""

from __future__ import annotations

import tempfile
import uuid
from collections.abc import Callable, Iterator

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

#: A word is a run of bytes other than space and U+0009 to U+000D.
WORD = r"[^\x20\x09-\x0D]+"


#: Rows of whole texts that go to Python at once.
ROWS = 1024


def documents(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/documents.parquet")


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share: spark.checkpoint.dir, or one of our own where it is unset (tests)."""
    for where in (spark.conf.get("spark.checkpoint.dir", None), spark.sparkContext.getConf().get("spark.checkpoint.dir"), spark.sparkContext.getCheckpointDir()):
        if where:
            return where.rstrip("/")
    if not spark.sparkContext.master.startswith("local"):
        raise ValueError("set spark.checkpoint.dir to a folder that all executors share")
    own = "file://" + tempfile.mkdtemp(prefix="virtcol-")
    spark.sparkContext.setCheckpointDir(own)
    return own


class Scratch:
    """Intermediate tables of one operator call, written to the shared folder.

    A written table cuts lineage and outlives the executor that wrote it.
    """

    def __init__(self, spark: SparkSession, name: str):
        self.spark, self.root, self.n = spark, f"{shared_dir(spark)}/virtcol-{name}-{uuid.uuid4().hex[:12]}", 0

    def keep(self, df: DataFrame, name: str) -> DataFrame:
        self.n += 1
        path = f"{self.root}/{self.n}-{name}"
        df.write.option("compression", "zstd").parquet(path)
        out = self.spark.read.schema(df.schema).parquet(path)
        out._scratch_path = path
        return out

    def drop(self, df: DataFrame | None) -> None:
        """Remove a kept table that nothing reads any more."""
        if path := getattr(df, "_scratch_path", None):
            p = self.spark._jvm.org.apache.hadoop.fs.Path(path)
            p.getFileSystem(self.spark._jsc.hadoopConfiguration()).delete(p, True)


def text_or_empty(col: str) -> Column:
    return F.coalesce(F.col(col).cast("string"), F.lit(""))


def row_key(id_col: str, text_col: str) -> Column:
    """16 bytes that name a row by its id and text, so a second scan finds it again whatever the order of rows.

    Rows that are equal in both get equal keys; operators give them equal results.
    """
    return F.unhex(F.md5(F.concat_ws("\x1f", F.coalesce(F.col(id_col).cast("string"), F.lit("null")), F.octet_length(text_or_empty(text_col)).cast("string"), text_or_empty(text_col)).cast("binary")))


def arrow_pass(df: DataFrame, schema: str | T.StructType, make: Callable[[], Callable[[pa.RecordBatch], Iterator[pa.RecordBatch] | pa.RecordBatch]], keep: str = "") -> DataFrame:
    """mapInArrow; make() runs once a task and returns what turns one batch into one or several.

    A worker outlives its tasks: each pass first lets go of what per_process() holds under another token than `keep`, and gives free memory back at its end.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        lean(keep)
        try:
            yield from through(batches)
        finally:
            lean(keep)

    def through(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        each = make()
        for b in batches:
            for part in small(b):
                out = each(part)
                if isinstance(out, pa.RecordBatch):
                    yield out
                else:
                    yield from out
        end = getattr(each, "end", None)
        if end is not None:
            yield from end()

    def small(b: pa.RecordBatch, rows: int = ROWS) -> Iterator[pa.RecordBatch]:
        for at in range(0, b.num_rows, rows):
            yield b.slice(at, rows)

    given = "spark.sql.execution.arrow.maxRecordsPerBatch"
    if df.sparkSession.conf.get(given) == "10000":  # the default, which holds tens of MB of text on both sides; what a user sets stays
        df.sparkSession.conf.set(given, str(ROWS))
    return df.mapInArrow(run, schema)


def add_columns(df: DataFrame, text_col: str, fields: str, make: Callable[[], Callable[[list[bytes]], list]], keep: str = "", drop: tuple[str, ...] = ()) -> DataFrame:
    """df with new columns made from its text: make() returns a function from a list of UTF-8 texts (null: empty) to one list or array per new column.

    A column of df with a new column's name is replaced; those in `drop` go; all others pass through.  The text goes to
    Python once, whether or not it is among them.
    """
    new = T._parse_datatype_string(fields)
    names = {f.name for f in new} | set(drop)
    kept = [f for f in df.schema.fields if f.name not in names]
    given = [F.col(f"`{f.name}`") for f in kept]
    at = next((i for i, f in enumerate(kept) if f.name == text_col and isinstance(f.dataType, T.StringType)), len(kept))
    ready = df.select(*given) if at < len(kept) else df.select(*given, text_or_empty(text_col).alias("__virtcol_text"))
    schema = T.StructType([*kept, *new])

    def build():
        work = make()

        def each(b: pa.RecordBatch) -> pa.RecordBatch:
            made = work([t or b"" for t in b.column(at).cast(pa.binary()).to_pylist()])
            arrays = [pa.array(x, type=k) if not isinstance(x, pa.Array) else x for x, k in zip(made, kinds, strict=True)]
            return pa.RecordBatch.from_arrays([*(b.column(i) for i in range(len(kept))), *arrays], names=[f.name for f in schema])

        return each

    from pyspark.sql.pandas.types import to_arrow_type

    kinds = [to_arrow_type(f.dataType) for f in new]
    return arrow_pass(ready, schema, build, keep)


def bounded_broadcast(df: DataFrame, most: int) -> DataFrame:
    """df marked for broadcast if it has at most so many rows; else as it is, and Spark joins by shuffle."""
    return F.broadcast(df) if df.limit(most + 1).count() <= most else df


def _held() -> dict:
    """What this Python worker holds between tasks: name -> (token, object)."""
    import sys
    import types

    return vars(sys.modules.setdefault("_virtcol_process", types.ModuleType("_virtcol_process"))).setdefault("held", {})


def per_process(name: str, token: str, build: Callable):
    """What build() makes, once for all tasks of a Python worker with the same token; a new token replaces the old one's."""
    held = _held()
    if held.get(name, ("",))[0] != token:
        held[name] = (token, build())
    return held[name][1]


def lean(keep: str = "") -> None:
    """Drop what other tokens hold, and hand free memory back to the system, which a worker that waits would else keep."""
    import ctypes
    import gc

    held = _held()
    for name in [n for n, (token, _) in held.items() if token != keep]:
        del held[name]
    gc.collect()
    pa.set_memory_pool(pa.system_memory_pool())
    try:
        ctypes.CDLL(None).malloc_trim(0)
    except AttributeError:  # a C library without it
        pass
