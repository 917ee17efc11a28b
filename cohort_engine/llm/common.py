"""Helpers that the training-data operators share."""

from __future__ import annotations

import tempfile
from collections.abc import Callable, Iterator
from contextlib import contextmanager

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

#: Rows of one Arrow batch; with long texts this bounds what a Python worker holds.
BATCH_ROWS = 1024


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def let(value: Column, body: Callable[[Column], Column]) -> Column:
    """``body`` over a value that is computed once for the row, however often ``body`` names it."""
    return F.get(F.transform(F.array(value), lambda v: body(v)), F.lit(0))


def total(values: Column, kind: str = "bigint") -> Column:
    return F.aggregate(values, F.lit(0).cast(kind), lambda a, x: a + x.cast(kind))


def numbered(df: DataFrame) -> DataFrame:
    """``df`` with its columns called ``_0, _1, ...``, so that no name of a caller's column meets one of an operator's own."""
    return df.toDF(*(f"_{k}" for k in range(len(df.columns))))


def words_of(text: Column) -> Column:
    """Runs of characters other than blank, tab, line feed, vertical tab, form feed and carriage return."""
    return F.array_remove(F.split(text, r"[\x20\x09-\x0D]+"), "")


def shared_folder(spark: SparkSession) -> str:
    """The folder that the cluster shares: that of ``spark.checkpoint.dir``.

    Without that setting a folder of this machine is made, but only for a local master, as in tests: on a
    cluster each executor would write to its own disk, so there the setting is asked for."""
    context = spark.sparkContext
    if context.getCheckpointDir() is None:
        folder = spark.conf.get("spark.checkpoint.dir", None)
        if folder is None:
            if not context.master.split("[")[0] == "local":
                raise RuntimeError("spark.checkpoint.dir must name a folder that all executors share")
            folder = tempfile.mkdtemp(prefix="checkpoints-")
        context.setCheckpointDir(folder)
    return context.getCheckpointDir()


@contextmanager
def swept(spark: SparkSession) -> Iterator[None]:
    """Frames that are made and run inside leave no files of their shuffles: Spark deletes these as the action ends, and not only when the
    driver collects its garbage, which can be many rounds later. Spark reads the setting when a frame is made, so it is taken back at the end."""
    name = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"
    before = spark.conf.get(name, "false")
    spark.conf.set(name, "true")
    try:
        yield
    finally:
        spark.conf.set(name, before)


def cut(df: DataFrame) -> DataFrame:
    """The same rows with their lineage cut: a checkpoint in the shared folder. What was shuffled on the way is deleted."""
    shared_folder(df.sparkSession)
    with swept(df.sparkSession):
        return df.select("*").checkpoint()


def has_rows(df: DataFrame) -> bool:
    """Whether there is a row. What was shuffled for that is deleted, which ``isEmpty`` would leave."""
    with swept(df.sparkSession):
        return bool(df.select(F.lit(1)).head(1))


def drop_folder(spark: SparkSession, path: str) -> None:
    """Deletes a folder that was written by Spark, wherever it is."""
    jvm = spark.sparkContext._jvm
    at = jvm.org.apache.hadoop.fs.Path(path)
    at.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(at, True)


#: Up to so many keys of 16 bytes are sent to all executors.
FEW_KEYS = 200_000


def row_key(id_col: Column, text: Column) -> Column:
    """Sixteen bytes that are equal for rows of equal id and text (a null text counts as empty)."""
    return F.unhex(F.md5(F.concat_ws("|", F.coalesce(id_col.cast("string"), F.lit("")), F.coalesce(text, F.lit("")))))


def keep_keys(docs: DataFrame, id_col: str, text_col: str, keys: DataFrame, winners: DataFrame) -> DataFrame:
    """The rows of ``docs`` whose key is among ``winners`` (``key``), one of each; ``keys`` has the key of every row.

    What goes is looked for, as it is mostly less than what stays: few keys are sent to the executors, and then no text is moved; more
    are joined by key, which moves each text once."""
    counts = keys.groupBy("key").agg(F.count("*").alias("n"))
    losers = cut(counts.join(winners.select("key"), "key", "left_anti").select("key"))
    few = losers.count() <= FEW_KEYS
    held = numbered(docs)
    held = held.withColumn("key", row_key(*(F.col(f"_{place_of(docs, c)}") for c in (id_col, text_col))))
    kept = held.join(F.broadcast(losers) if few else losers, "key", "left_anti")
    if has_rows(counts.where("n > 1")):
        kept = kept.dropDuplicates(["key"])
    return kept.drop("key").toDF(*docs.columns)


def small_batches(spark: SparkSession) -> None:
    """Lets Spark send batches of up to ``BATCH_ROWS`` rows to Python. It is a setting of the session that Spark reads when a plan runs, so it
    can't be given to one plan, nor taken back while a result has yet to be read; it is only ever lowered. With batches of Spark's own
    size an executor's Arrow buffers take several hundred MB."""
    name = "spark.sql.execution.arrow.maxRecordsPerBatch"
    if not 0 < int(spark.conf.get(name)) <= BATCH_ROWS:
        spark.conf.set(name, str(BATCH_ROWS))


def slices(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """The batches in pieces of up to ``BATCH_ROWS`` rows, so that few texts at a time are Python objects."""
    for batch in batches:
        for at in range(0, batch.num_rows, BATCH_ROWS):
            yield batch.slice(at, BATCH_ROWS)


def map_columns(df: DataFrame, fn: Callable[[dict[str, list]], dict[str, list]], schema: str) -> DataFrame:
    """``fn`` from the columns of a batch, as Python lists, to the columns of its result.

    The result may have any number of rows; batches are small, so memory is bounded by the
    longest texts, not by the partition."""
    small_batches(df.sparkSession)
    kinds = arrow_schema(schema)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in slices(batches):
            got = fn({n: c.to_pylist() for n, c in zip(batch.schema.names, batch.columns, strict=True)})
            yield pa.RecordBatch.from_arrays([as_arrow(got[f.name], f.type) for f in kinds], schema=kinds)
        pa.default_memory_pool().release_unused()

    return df.mapInArrow(run, schema)


def as_arrow(values: list | pa.Array, kind: pa.DataType) -> pa.Array:
    return values if isinstance(values, pa.Array) else pa.array(values, kind)


def arrow_schema(schema: str) -> pa.Schema:
    from pyspark.sql.pandas.types import to_arrow_schema

    return to_arrow_schema(T._parse_datatype_string(schema))


def place_of(df: DataFrame, name: str) -> int:
    """Where a column stands; names are compared as the session does."""
    if name in df.columns or df.sparkSession.conf.get("spark.sql.caseSensitive") == "true":
        return df.columns.index(name)
    return [c.lower() for c in df.columns].index(name.lower())


def add_columns(df: DataFrame, inputs: list[str], fn: Callable[[dict[str, list]], dict[str, list]], schema: str, keep: str | None = None) -> DataFrame:
    """``df`` with the columns of ``schema``, computed from ``inputs`` batch by batch; no shuffle.

    Columns of ``df`` that are not among the inputs stay in Arrow form. A new column takes the
    place of old ones of the same name, compared as the session does. ``keep``: a boolean column of the result; rows where
    it is false go, and it goes too."""
    small_batches(df.sparkSession)
    kinds = arrow_schema(schema)
    same = str if df.sparkSession.conf.get("spark.sql.caseSensitive") == "true" else str.lower
    added = {same(f.name): f for f in T._parse_datatype_string(schema).fields if f.name != keep}
    sources = {n: place_of(df, n) for n in inputs}
    plan: list[tuple[T.StructField, int | None]] = []
    for k, f in enumerate(df.schema.fields):
        new = added.get(same(f.name))
        if new is None:
            plan.append((f, k))
        elif (new, None) not in plan:
            plan.append((new, None))
    plan += [(f, None) for f in added.values() if (f, None) not in plan]
    # numbered on the way, so that no two names meet
    out = T.StructType([T.StructField(f"_{k}", f.dataType, True) for k, (f, _) in enumerate(plan)])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in slices(batches):
            got = fn({n: batch.column(k).to_pylist() for n, k in sources.items()})
            new = {f.name: as_arrow(got[f.name], f.type) for f in kinds}
            made = pa.RecordBatch.from_arrays([new[f.name] if k is None else batch.column(k) for f, k in plan], names=out.names)
            yield made.filter(new[keep]) if keep else made
        pa.default_memory_pool().release_unused()

    return df.mapInArrow(run, out).toDF(*(f.name for f, _ in plan))
