"""The compressed layout: chunks of whole users, dictionaries of two levels, ranges of two levels, packed words.

A table of chunks has one row for each chunk, and a column of packed words for each column of the activity table, so a reader
takes from the files what a plan needs. Users are kept as runs (user, first row, rows). A string column has a dictionary of the whole table, in
order, and in each chunk a dictionary of the global ids that occur there; tuples hold places in that. A numeric column has the
range of the whole table, in each chunk a range relative to it, and in the tuples differences from the chunk's
minimum (0 is kept for null).

Numbers are exact: times are microseconds, whole numbers and decimals stand for themselves, and doubles are kept in the coarsest decimal unit
that gives every value of the column back, or, if there is none, by their 64 bits in an order that is that of the numbers. NaN counts as null."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.pandas.types import to_arrow_schema

from ..functions.bits import pack
from ..functions.lineage import cut, drop_folder, fresh_folder
from ..schema import ActivityTable, CohortSemanticError

CHUNK_ROWS = 262_144
_PACKED = "struct<low:bigint,nulls:boolean,bits:int,words:array<bigint>>"
#: Decimal units that doubles may be kept in, as places.
UNITS = range(7)


@dataclass(frozen=True)
class Number:
    """How a numeric column is kept: ``int`` as it is, ``scaled`` in parts of ``scale``, ``float`` by its bits; ``low, high``: the table's range."""

    kind: str
    scale: int = 1
    low: int = 0
    high: int = -1

    def stored(self, values: np.ndarray) -> np.ndarray:
        """Values, none of them null, as signed whole numbers in the same order."""
        if self.kind == "scaled":
            return np.rint(values.astype(np.float64) * self.scale).astype(np.int64)
        return ordered_bits(values) if self.kind == "float" else values.astype(np.int64)

    def real(self, stored: np.ndarray) -> np.ndarray:
        """The values again."""
        if self.kind == "scaled":
            return stored / self.scale
        return from_ordered_bits(stored) if self.kind == "float" else stored

    def bounds(self, value: object) -> tuple[int, int]:
        """Stored numbers that no value below ``value`` exceeds and that no value above it falls short of."""
        if self.kind == "float":
            b = int(ordered_bits(np.array([float(value)]))[0])
            return b, b
        x = value * self.scale
        return int(np.floor(x)) - (self.scale > 1), int(np.ceil(x)) + (self.scale > 1)


def ordered_bits(x: np.ndarray) -> np.ndarray:
    """Doubles as signed numbers in the same order."""
    b = (np.asarray(x, np.float64) + 0.0).view(np.int64)
    return np.where(b >= 0, b, b ^ np.int64(0x7FFFFFFFFFFFFFFF))


def from_ordered_bits(k: np.ndarray) -> np.ndarray:
    k = np.asarray(k, np.int64)
    return np.where(k >= 0, k, k ^ np.int64(0x7FFFFFFFFFFFFFFF)).view(np.float64)


@dataclass(frozen=True)
class Chunks:
    """``chunks``: a row for each chunk, columns by :meth:`field`. ``dictionary``: ``column, value, gid`` of all string columns.
    ``catalog``: what pruning needs: the global ids of each string column, and each numeric column's range, by chunk."""

    path: str
    chunks: DataFrame
    dictionary: DataFrame
    catalog: DataFrame
    strings: tuple[str, ...]
    numbers: dict[str, Number]

    def field(self, column: str) -> str:
        """What a column is called in the files."""
        return f"c{[*self.strings, *self.numbers].index(column)}"

    def drop(self) -> None:
        drop_folder(self.chunks.sparkSession, self.path)


def numbered(df: DataFrame, order: list[str], weight: str | None = None) -> DataFrame:
    """``df`` with ``place``: how many rows (or how much weight) come before, in order; ranges are summed apart from each other."""
    spread = cut(df.repartitionByRange(*order).withColumn("_part", F.spark_partition_id()))
    w = F.lit(1) if weight is None else F.col(weight)
    inside = F.sum(w).over(Window.partitionBy("_part").orderBy(*order).rowsBetween(Window.unboundedPreceding, -1))
    sums = spread.groupBy("_part").agg(F.sum(w).alias("_sum"))
    offset = F.coalesce(F.sum("_sum").over(Window.orderBy("_part").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    sums = sums.select("_part", offset.alias("_offset"))  # a row for each partition
    return spread.withColumn("_inside", F.coalesce(inside, F.lit(0))).join(F.broadcast(sums), "_part").withColumn("place", F.col("_offset") + F.col("_inside")).drop("_part", "_inside", "_offset")


def _dictionary(values: DataFrame) -> DataFrame:
    """``column, value, gid`` of ``column, value``: the distinct values of each column in order, numbered from 0."""
    placed = numbered(values.where("value IS NOT NULL").distinct(), ["column", "value"])
    first = placed.groupBy(F.col("column").alias("_c")).agg(F.min("place").alias("_first"))  # a row for each column
    return placed.join(F.broadcast(first), F.col("column") == F.col("_c")).select("column", "value", (F.col("place") - F.col("_first")).cast("bigint").alias("gid"))


def global_dictionary(df: DataFrame, column: str) -> DataFrame:
    """``value, gid``: the distinct values in order, numbered from 0."""
    return _dictionary(df.select(F.lit(column).alias("column"), F.col(column).cast("string").alias("value"))).select("value", "gid")


def assign_chunks(act: ActivityTable, rows: int = CHUNK_ROWS, mode: str = "hash", total: int | None = None) -> DataFrame:
    """The table with ``chunk_id``; a user is in one chunk. ``range``: neighbours in order of users share chunks."""
    user = act.schema.user
    if mode == "hash":
        n = max(1, -(-(act.df.count() if total is None else total) // rows))
        return act.df.withColumn("chunk_id", F.pmod(F.xxhash64(user), F.lit(n)).cast("bigint"))
    per = act.df.groupBy(user).agg(F.count("*").alias("_n"))
    placed = numbered(per, [user], "_n").select(F.col(user).alias("_u"), F.floor(F.col("place") / rows).cast("bigint").alias("chunk_id"))
    return act.df.join(placed, F.col(user) == F.col("_u")).drop("_u")


def _whole(kind: T.DataType, column: str) -> Column | None:
    """A column as whole numbers, if its type is one that has them."""
    c = F.col(column)
    if isinstance(kind, T.TimestampNTZType | T.TimestampType):
        zone = "TIMESTAMP_NTZ" if isinstance(kind, T.TimestampNTZType) else "TIMESTAMP"
        return F.expr(f"timestampdiff(MICROSECOND, {zone}'1970-01-01 00:00:00', `{column}`)")
    if isinstance(kind, T.DateType):
        return F.expr(f"datediff(`{column}`, DATE'1970-01-01') * 86400000000L")
    if isinstance(kind, T.DecimalType):
        if kind.precision > 18:
            raise CohortSemanticError(f"{column!r} has more than 18 digits; chunks keep 64 bits")
        return (c * 10**kind.scale).cast("bigint")
    return None if isinstance(kind, T.DoubleType | T.FloatType) else c.cast("bigint")


def measured(act: ActivityTable, numbers: list[str]) -> tuple[int, dict[str, Number], dict[str, Column]]:
    """Rows of the table, how each numeric column is kept, and the columns as they are encoded: one pass over the table."""
    aggs, made, kinds = [F.count("*").alias("rows")], {}, {}
    for k, c in enumerate(numbers):
        kind = act.df.schema[c].dataType
        whole = _whole(kind, c)
        x = F.col(c).cast("double") if whole is None else whole
        x = F.when(F.isnan(x), None).otherwise(x) if whole is None else x
        made[c], kinds[c] = x, (kind, whole is not None)
        aggs += [F.min(x).alias(f"low{k}"), F.max(x).alias(f"high{k}")]
        if whole is None:
            aggs += [F.bool_and((F.rint(x * 10**u) / 10**u == x) & (F.abs(x) < 2.0**53 / 10**u)).alias(f"fits{k}_{u}") for u in UNITS]
    seen = act.df.agg(*aggs).first()
    out = {}
    for k, c in enumerate(numbers):
        kind, whole = kinds[c]
        fits = None if whole else next((u for u in UNITS if seen[f"fits{k}_{u}"]), None)
        number = Number("scaled" if isinstance(kind, T.DecimalType) and kind.scale else "int", 10**kind.scale if isinstance(kind, T.DecimalType) else 1) if whole else Number("float") if fits is None else Number("scaled", 10**fits)
        if seen[f"low{k}"] is not None:
            ends = np.array([seen[f"low{k}"], seen[f"high{k}"]])
            low, high = (ends if whole else number.stored(ends)).tolist()
            number = Number(number.kind, number.scale, int(low), int(high))
        out[c] = number
    return seen["rows"], out, made


def user_runs(users: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Users, first rows and row counts of a column that is sorted by user."""
    firsts = np.flatnonzero(np.concatenate([[True], users[1:] != users[:-1]])) if len(users) else np.zeros(0, np.int64)
    return users[firsts], firsts, np.diff(np.concatenate([firsts, [len(users)]]))


def _packed(codes: np.ndarray, null: np.ndarray, low: int) -> dict:
    """Codes from 0 on; where anything is null, codes are moved by one and 0 stands for null."""
    some = bool(null.any())
    if some:
        codes = np.where(null, np.uint64(0), codes + np.uint64(1))
    bits, words = pack(codes)
    return {"low": low, "nulls": some, "bits": bits, "words": words.tolist()}


def _one(column: pa.ChunkedArray) -> pa.Array:
    return column.combine_chunks() if column.num_chunks != 1 else column.chunk(0)


def _encoded(table: pa.Table, strings: list[str], numbers: dict[str, Number], whole: set[str], schema: pa.Schema) -> pa.Table:
    table = table.sort_by("_order")
    users, firsts, counts = user_runs(np.asarray(table.column("_user").to_pylist(), dtype=object))
    row = {"chunk_id": table.column("chunk_id")[0].as_py(), "n_rows": len(table), "n_users": len(users), "users": [str(u) for u in users], "firsts": firsts.tolist(), "counts": counts.tolist()}
    size = 12 * len(users)
    for k in range(len(strings)):
        made = pc.dictionary_encode(_one(table.column(f"c{k}")))
        order = pc.sort_indices(made.dictionary).to_numpy()
        place = np.empty(len(order) + 1, np.uint64)
        place[order], place[-1] = np.arange(len(order), dtype=np.uint64), 0
        null = made.indices.is_null().to_numpy(zero_copy_only=False)
        row[f"c{k}"] = _packed(place[made.indices.fill_null(len(order)).to_numpy(zero_copy_only=False)], null, 0)
        row[f"d{k}"] = made.dictionary.take(pa.array(order)).to_pylist()
        size += 8 * len(row[f"c{k}"]["words"]) + 4 * len(order) + 20
    for k, (name, number) in enumerate(numbers.items(), len(strings)):
        column = _one(table.column(f"c{k}"))
        null = column.is_null().to_numpy(zero_copy_only=False)
        known = column.drop_null().to_numpy(zero_copy_only=False)
        stored = known if name in whole else number.stored(known)
        # differences are taken as unsigned numbers, so that a range of all doubles fits
        apart = stored.astype(np.int64).view(np.uint64) - np.array([number.low], np.int64).view(np.uint64)
        low = apart.min() if len(apart) else np.uint64(0)
        codes = np.zeros(len(table), np.uint64)
        codes[~null] = apart - low
        row[f"c{k}"] = _packed(codes, null, int(np.array([low]).view(np.int64)[0]))
        row[f"l{k}"], row[f"h{k}"] = (int(stored.min()), int(stored.max())) if len(stored) else (None, None)
        size += 8 * len(row[f"c{k}"]["words"]) + 20
    return pa.Table.from_pylist([row | {"bytes": size}], schema=schema)


def compress(act: ActivityTable, rows: int = CHUNK_ROWS, mode: str = "hash", path: str | None = None) -> Chunks:
    """Encodes a table and writes it to ``path``, or to a folder in the shared one. A task holds one chunk, so users far larger than ``rows``
    call for another layout.

    The table is read once for its ranges and shuffled once by chunk; dictionaries are made from those of the chunks."""
    s, spark = act.schema, act.df.sparkSession
    path = path or fresh_folder(spark, "chunks")
    strings = [c for c in s.columns if c != s.user and isinstance(act.df.schema[c].dataType, T.StringType)]
    total, numbers, made = measured(act, [c for c in s.columns if c not in (s.user, *strings)])
    df = assign_chunks(act, rows, mode, total)
    names = [*strings, *numbers]
    whole = {c for c in numbers if not isinstance(act.df.schema[c].dataType, T.DoubleType | T.FloatType)}
    order = F.row_number().over(Window.partitionBy("chunk_id").orderBy(s.user, s.time, *s.tie_break, s.action))
    flat = df.select("chunk_id", F.col(s.user).alias("_user"), order.alias("_order"), *(made.get(c, F.col(c)).alias(f"c{k}") for k, c in enumerate(names)))
    kinds = ["chunk_id bigint, n_rows bigint, n_users bigint, users array<string>, firsts array<int>, counts array<int>"]
    kinds += [f"c{k} {_PACKED}, d{k} array<string>" if c in strings else f"c{k} {_PACKED}, l{k} bigint, h{k} bigint" for k, c in enumerate(names)]
    ddl = ", ".join([*kinds, "bytes bigint"])
    schema = to_arrow_schema(T._parse_datatype_string(ddl))
    flat.groupBy("chunk_id").applyInArrow(lambda t: _encoded(t, strings, numbers, whole, schema), ddl).write.parquet(f"{path}/chunks")
    chunks = spark.read.parquet(f"{path}/chunks")
    if strings:
        held = F.array(*(F.struct(F.lit(c).alias("column"), F.col(f"d{k}").alias("values")) for k, c in enumerate(strings)))
        each = chunks.select("chunk_id", F.explode(held).alias("e")).select("chunk_id", F.col("e.column").alias("column"), F.posexplode("e.values").alias("at", "value"))
    else:
        each = spark.createDataFrame([], "chunk_id bigint, column string, at int, value string")
    _dictionary(each.select("column", "value")).write.parquet(f"{path}/dictionary")
    dictionary = spark.read.parquet(f"{path}/dictionary")
    placed = each.join(dictionary, ["column", "value"]).groupBy("chunk_id", "column").agg(F.sort_array(F.collect_list(F.struct("at", "gid")))["gid"].alias("gids"))
    gids = placed.groupBy("chunk_id").agg(F.map_from_entries(F.collect_list(F.struct("column", "gids"))).alias("gids"))
    ranges = [(f"{e}{k}", f"{e}{k}") for k, c in enumerate(names) if c in numbers for e in "lh"]
    catalog = chunks.select("chunk_id", "n_rows", "n_users", "bytes", *(a for a, _ in ranges)).join(gids, "chunk_id", "left")
    catalog.write.parquet(f"{path}/catalog")
    return Chunks(path, chunks, dictionary, spark.read.parquet(f"{path}/catalog"), tuple(strings), numbers)


def storage(chunks: Chunks) -> DataFrame:
    """Bytes of the encoded chunks, and what they hold."""
    return chunks.catalog.agg(F.count("*").alias("chunks"), F.sum("n_rows").alias("rows"), F.sum("n_users").alias("users"), F.sum("bytes").alias("bytes"))
