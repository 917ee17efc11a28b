"""The chunked executor: works on encoded chunks, user block by user block, and reads packed values only where it needs them.

Chunks that can't hold a qualified birth are pruned by the catalog, and chunks without an activity that can meet the age condition give
only sizes of cohorts. In a chunk, the actions of each block are read up to the user's birth and no further; conditions on the birth tuple read
their columns at the births alone, one after another, for the users that are left; the blocks of all other users are skipped.
Of a qualified user's block the tuples after birth are read, up to the last age that the plan allows, and of
these the time and the measures of tuples that meet the conditions on the tuple. Every read is by place in the packed words, and is counted.

Cells go into dense arrays by cohort and age. A user is in one chunk, so distinct users are counted inside chunks and
partial results just add up."""

from __future__ import annotations

from collections.abc import Callable, Iterator
from dataclasses import dataclass, field, replace
from decimal import ROUND_HALF_UP, Decimal

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..functions.ages import _MICROS, TimeBin
from ..functions.bits import read_many
from ..functions.measures import PLACES
from ..functions.predicates import Age, And, Attr, Between, Birth, Cmp, Days, In, Lit, Not, Or, Pred, age_limit, birth_attributes, conjoin, conjuncts, on_arrays, split, uses_age
from ..plans.algebra import CohortPlan, normalise
from ..schema import CohortSemanticError
from .encode import Chunks, Number, compress


class PackedColumn:
    """A column of a chunk. Values are read by their places; ``reads`` counts them."""

    def __init__(self, bits: int, words: np.ndarray, low: int, nulls: bool, number: Number | None, gids: np.ndarray | None) -> None:
        self.bits, self.words, self.low, self.nulls, self.number, self.gids = bits, words, low, nulls, number, gids
        self.reads = 0

    def codes(self, places: np.ndarray) -> np.ndarray:
        self.reads += len(places)
        return read_many(self.bits, self.words, places)

    def code_of(self, gid: int) -> int | None:
        """The code that stands for a global id, if the chunk has it."""
        at = int(np.searchsorted(self.gids, gid)) if len(self.gids) else 0
        return at + self.nulls if at < len(self.gids) and self.gids[at] == gid else None

    def stored(self, places: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Stored whole numbers (of a string column global ids), and where they are null; those have no meaning."""
        codes = self.codes(places)
        null = codes == 0 if self.nulls else np.zeros(len(codes), bool)
        codes = codes - np.uint64(1) if self.nulls else codes
        if self.number is None:
            return np.append(self.gids, -1)[np.where(null, len(self.gids), codes).astype(np.int64)], null
        base = np.array([self.low, self.number.low], np.int64).view(np.uint64)
        return (codes + base[0] + base[1]).view(np.int64), null

    def real(self, places: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        stored, null = self.stored(places)
        return (stored if self.number is None else self.number.real(stored)), null

    def values(self, places: np.ndarray) -> np.ndarray:
        """Values for predicates: numbers, or objects with None where something is null."""
        real, null = self.real(places)
        if not null.any():
            return real
        if real.dtype.kind == "f":
            return np.where(null, np.nan, real)
        out = real.astype(object)
        out[null] = None
        return out


class UserBlocks:
    """A chunk's tuples as blocks of users, each in order of time."""

    def __init__(self, firsts: np.ndarray, counts: np.ndarray) -> None:
        self.firsts, self.counts, self.ends = firsts, counts, firsts + counts

    @staticmethod
    def places(starts: np.ndarray, sizes: np.ndarray) -> np.ndarray:
        """All places of runs, run by run."""
        before = np.cumsum(sizes) - sizes
        return np.repeat(starts - before, sizes) + np.arange(int(sizes.sum()))

    def find_births(self, action: PackedColumn, code: int | None, step: int = 4) -> np.ndarray:
        """The first place of each block with the action, which is the birth; -1 for users without one.

        Blocks are read side by side, a few tuples each, then twice as many; a block whose birth is found is left."""
        births = np.full(len(self.firsts), -1, np.int64)
        if code is None:
            return births
        open_, at = np.arange(len(self.firsts)), self.firsts.astype(np.int64)
        while len(open_):
            sizes = np.minimum(step, self.ends[open_] - at[open_])
            places = self.places(at[open_], sizes)
            hit = np.flatnonzero(action.codes(places) == code)
            owner, first = np.unique(np.repeat(np.arange(len(open_)), sizes)[hit], return_index=True)
            births[open_[owner]] = places[hit[first]]
            at[open_] += sizes
            open_ = open_[(births[open_] < 0) & (at[open_] < self.ends[open_])]
            step *= 2
        return births


@dataclass(frozen=True)
class ChunkOptions:
    prune: bool = True
    push_birth: bool = True


@dataclass(frozen=True)
class _Literals:
    """Global ids of a plan's strings, and how many values come before each."""

    ids: dict[tuple[str, str], int]
    below: dict[tuple[str, str], int]


def _on_codes(p: Pred | None, chunks: Chunks, time: str, known: _Literals, user: str) -> Pred | None:
    """The predicate over what columns read as: strings become global ids, which are in order of the strings, and times microseconds."""
    if p is None:
        return None
    again = lambda q: _on_codes(q, chunks, time, known, user)
    if isinstance(p, And | Or):
        return replace(p, parts=tuple(map(again, p.parts)))
    if isinstance(p, Not):
        return Not(again(p.part))
    if isinstance(p, Days):
        return p
    name = p.left.name if isinstance(p.left, Attr | Birth) else None
    if name == user:
        raise CohortSemanticError("the chunked executor has no conditions on users")

    def number(v: object) -> object:
        return int(np.datetime64(v.replace(" ", "T"), "us").astype(np.int64)) if name == time and isinstance(v, str) else v

    if name in chunks.strings:
        if isinstance(p, In):
            return In(p.left, tuple(known.ids.get((name, v), -2) for v in p.values))
        if isinstance(p, Between):
            return And((again(Cmp(">=", p.left, Lit(p.low))), again(Cmp("<=", p.left, Lit(p.high)))))
        if isinstance(p.right, Lit):
            v = p.right.value
            if p.op in ("=", "!="):
                return Cmp(p.op, p.left, Lit(None if v is None else known.ids.get((name, v), -2)))
            first = known.below[(name, v)] + (1 if p.op in ("<=", ">") and (name, v) in known.ids else 0)
            return Cmp("<" if p.op in ("<", "<=") else ">=", p.left, Lit(first))
        if isinstance(p.right, Attr | Birth) and p.right.name != name:
            raise CohortSemanticError("the chunked executor compares strings of one column only")
        return p
    if isinstance(p, In):
        return In(p.left, tuple(map(number, p.values)))
    if isinstance(p, Between):
        return Between(p.left, number(p.low), number(p.high))
    return Cmp(p.op, p.left, Lit(number(p.right.value))) if isinstance(p.right, Lit) and not isinstance(p.left, Lit | Age) else p


def possible(p: Pred | None, chunks: Chunks) -> Column:
    """Whether a chunk may have a tuple that meets a predicate over codes: a look at its dictionaries and ranges. What says nothing of one
    tuple's own attributes is taken as possible."""
    if p is None:
        return F.lit(True)
    if isinstance(p, And | Or):
        out = possible(p.parts[0], chunks)
        for q in p.parts[1:]:
            out = out & possible(q, chunks) if isinstance(p, And) else out | possible(q, chunks)
        return out
    if isinstance(p, Not) or not isinstance(p.left, Attr):
        return F.lit(True)
    name = p.left.name
    if isinstance(p, Days):
        day = lambda d: int(np.datetime64(d, "us").astype(np.int64))
        return _meets(name, chunks, day(p.first), day(p.last) + 86_400_000_000 - 1)
    if isinstance(p, In):
        return possible(Or(tuple(Cmp("=", p.left, Lit(v)) for v in p.values)), chunks) if p.values else F.lit(False)
    if isinstance(p, Between):
        return possible(And((Cmp(">=", p.left, Lit(p.low)), Cmp("<=", p.left, Lit(p.high)))), chunks)
    if not isinstance(p.right, Lit) or p.op == "!=":
        return F.lit(True)
    value = p.right.value
    if value is None:
        return F.lit(False)  # a comparison with null is never true
    if name in chunks.strings:
        gids = F.col("gids")[name]
        if p.op == "=":
            return F.coalesce(F.array_contains(gids, F.lit(int(value)).cast("bigint")), F.lit(False))
        return F.coalesce(F.array_min(gids) < value if p.op == "<" else F.array_max(gids) >= value, F.lit(False))
    if isinstance(value, str) or name not in chunks.numbers:
        return F.lit(True)
    low, high = chunks.numbers[name].bounds(value)
    return _meets(name, chunks, low if p.op in ("=", ">", ">=") else None, high if p.op in ("=", "<", "<=") else None)


def _meets(name: str, chunks: Chunks, low: int | None, high: int | None) -> Column:
    """Whether a chunk's range meets an interval. Outside of the whole table's range no chunk does."""
    whole, k = chunks.numbers[name], chunks.field(name)[1:]
    if (low is not None and low > whole.high) or (high is not None and high < whole.low):
        return F.lit(False)
    out = F.col(f"l{k}").isNotNull()
    if low is not None:
        out = out & (F.col(f"h{k}") >= low)
    return out if high is None else out & (F.col(f"l{k}") <= high)


def _words(p: Pred | None) -> set[tuple[str, str]]:
    """String literals with the columns that they are compared with."""
    if p is None:
        return set()
    if isinstance(p, And | Or):
        return {w for q in p.parts for w in _words(q)}
    if isinstance(p, Not):
        return _words(p.part)
    if isinstance(p, Days) or not isinstance(p.left, Attr | Birth):
        return set()
    values = p.values if isinstance(p, In) else (p.low, p.high) if isinstance(p, Between) else (p.right.value,) if isinstance(p.right, Lit) else ()
    return {(p.left.name, v) for v in values if isinstance(v, str)}


def _ages(unit, mode: str, time: np.ndarray, born: np.ndarray) -> np.ndarray:
    raw = time - born
    if unit == "tick":
        return raw
    if unit in _MICROS and mode in ("ceil", "floor1"):
        size = _MICROS[unit]
        return (raw + size - 1) // size if mode == "ceil" else raw // size + 1
    t, b = time.astype("datetime64[us]"), born.astype("datetime64[us]")
    more = mode == "calendar1"
    if unit == "month":
        months = (t.astype("datetime64[M]") - b.astype("datetime64[M]")).astype(np.int64)
        rest_t, rest_b = t - t.astype("datetime64[M]"), b - b.astype("datetime64[M]")
        if mode == "ceil":
            return months + (rest_t > rest_b)
        if mode == "floor1":
            return months - (rest_t < rest_b) + 1
        return months + more
    if unit == "hour":
        return (t.astype("datetime64[h]") - b.astype("datetime64[h]")).astype(np.int64) + more
    days = lambda x: x.astype("datetime64[D]").astype(np.int64)
    if unit == "day":
        return days(t) - days(b) + more
    return (days(t) + 4) // 7 - (days(b) + 4) // 7 + more  # 1970-01-01 was a Thursday; weeks start on Sunday


def _bin(unit: str, born: np.ndarray) -> np.ndarray:
    """The first day of a bin, in days from 1970."""
    days = born.astype("datetime64[us]").astype("datetime64[D]").astype(np.int64)
    if unit == "week":
        return days - (days + 4) % 7
    return days if unit == "day" else days.astype("datetime64[D]").astype("datetime64[M]").astype("datetime64[D]").astype(np.int64)


COUNTERS = ("users_visited", "users_skipped", "birth_probes", "age_tuples", "values_read")


def _key_kind(plan: CohortPlan, chunks: Chunks, b: str | TimeBin) -> T.DataType:
    doubles = not isinstance(b, TimeBin) and b in chunks.numbers and isinstance(plan.table.df.schema[b].dataType, T.DoubleType | T.FloatType)
    return T.DoubleType() if doubles else T.LongType()


def _fields(plan: CohortPlan, chunks: Chunks) -> list[T.StructField]:
    """Columns of partial rows: cohort, age (0 for sizes, -1 for counters), size, states of measures, counters."""
    kinds = {"s": T.DecimalType(38, PLACES), "m": T.DoubleType()}
    out = [T.StructField(f"k{i}", _key_kind(plan, chunks, b)) for i, b in enumerate(plan.by)]
    out += [T.StructField("age", T.LongType()), T.StructField("size", T.LongType())]
    out += [T.StructField(f"m{i}_{st}", kinds.get(st, T.LongType())) for i, (_, m) in enumerate(plan.measures) for st in m.partial("x")]
    return out + [T.StructField(c, T.LongType()) for c in COUNTERS]


def _exact_sums(column: PackedColumn, stored: np.ndarray, cell: np.ndarray, cells: int) -> list[Decimal]:
    """Sums by cell of stored numbers, as decimals; values without a unit are rounded as SQL does."""
    number = column.number
    if number.kind == "float":
        values, which = np.unique(stored, return_inverse=True)
        unit = Decimal(1).scaleb(-PLACES)
        whole = [int(Decimal(repr(float(v))).quantize(unit, ROUND_HALF_UP).scaleb(PLACES)) for v in number.real(values)]
        totals = [0] * cells
        for c, w in zip(cell.tolist(), which.tolist(), strict=True):
            totals[c] += whole[w]
        return [Decimal(t).scaleb(-PLACES) for t in totals]
    # halves are summed apart, so that no sum overflows
    high, low = np.zeros(cells, np.int64), np.zeros(cells, np.int64)
    np.add.at(high, cell, stored >> 32)
    np.add.at(low, cell, stored & 0xFFFFFFFF)
    places = len(str(number.scale)) - 1
    return [Decimal(int(h) * (1 << 32) + int(x)).scaleb(-places) for h, x in zip(high, low, strict=True)]


@dataclass
class _Chunk:
    """One chunk as it is read: a column is unpacked nowhere, only read at places."""

    blocks: UserBlocks
    columns: dict[str, PackedColumn]
    ages_possible: bool = True
    rows: dict[str, list] = field(default_factory=dict)

    def values(self, name: str, places: np.ndarray) -> np.ndarray:
        return self.columns[name].values(places)


def _narrowed(cond: Pred | None, places: np.ndarray, attr: Callable[[str, np.ndarray], np.ndarray], birth=None, age=None) -> np.ndarray:
    """Which of the places meet a condition; conjuncts are tested one after another, each on what is left."""
    left = np.arange(len(places))
    for c in conjuncts(cond):
        if not len(left):
            break
        own = None if birth is None else lambda a: birth(a, left)  # noqa: B023
        left = left[on_arrays(c, len(left), lambda a: attr(a, places[left]), own, None if age is None else age[left].astype(np.float64))]  # noqa: B023
    return left


def _partials(plan: CohortPlan, chunk: _Chunk, gid: int, birth_cond: Pred | None, age_cond: Pred | None, strings: tuple[str, ...], push: bool) -> dict[str, list]:
    s, blocks = plan.table.schema, chunk.blocks
    names = [*(f"k{i}" for i in range(len(plan.by))), "age", "size", *(f"m{i}_{st}" for i, (_, m) in enumerate(plan.measures) for st in m.partial("x"))]
    out: dict[str, list] = {n: [] for n in (*names, *COUNTERS)}

    def emit(n: int, **columns: object) -> None:
        for name in out:
            got = columns.get(name)
            out[name] += list(got) if isinstance(got, (list, np.ndarray)) else [0 if got is None and name in COUNTERS else got] * n

    action = chunk.columns[s.action]
    births = blocks.find_births(action, action.code_of(gid))
    probes = action.reads
    born = np.flatnonzero(births >= 0)
    ok = born[_narrowed(birth_cond, births[born], chunk.values)]
    users = ok if push else born
    kept = np.isin(users, ok)
    # the tuples after birth, up to the last age that the plan allows
    starts, ends = births[users] + 1, blocks.ends[users]
    time = chunk.columns[s.time]
    born_at = time.stored(births[users])[0]
    limit = age_limit(age_cond)
    if not chunk.ages_possible:
        ends = starts
    elif limit is not None and plan.age_unit.unit in _MICROS and plan.age_unit.mode == "ceil" and len(users):
        latest, low, high = born_at + limit * _MICROS[plan.age_unit.unit], starts.copy(), ends.copy()
        while (open_ := np.flatnonzero(low < high)).size:
            middle = (low[open_] + high[open_]) // 2
            late = time.stored(middle)[0] > latest[open_]
            high[open_[late]] = middle[late]
            low[open_[~late]] = middle[~late] + 1
        ends = low
    sizes = np.maximum(ends - starts, 0)
    places = blocks.places(starts, sizes)
    owner = np.repeat(np.arange(len(users)), sizes)

    keys = []
    for b in plan.by:
        if isinstance(b, TimeBin):
            keys.append((_bin(b.unit, born_at), np.zeros(len(users), bool)))
        else:
            keys.append(chunk.columns[b].stored(births[users]))
    stacked = np.stack([np.where(null, np.iinfo(np.int64).min, x) for x, null in keys], 1) if keys else np.zeros((len(users), 0), np.int64)
    if keys and len(users):
        cohorts, code = np.unique(stacked, axis=0, return_inverse=True)
        code = code.reshape(-1)
    else:
        cohorts, code = np.zeros((min(1, len(users)), len(keys)), np.int64), np.zeros(len(users), np.int64)

    def shown(which: np.ndarray) -> dict[str, list]:
        columns = {}
        for i, b in enumerate(plan.by):
            x = cohorts[which, i]
            number = None if isinstance(b, TimeBin) else chunk.columns[b].number
            doubles = number is not None and number.kind != "int" and not isinstance(plan.key_kinds[i], T.LongType)
            real = number.real(x) if doubles else x
            columns[f"k{i}"] = [None if v == np.iinfo(np.int64).min else r for v, r in zip(x.tolist(), real.tolist(), strict=True)]
        return columns

    own, rest = split(age_cond)
    left = _narrowed(own, places, chunk.values)
    places, owner = places[left], owner[left]
    at = time.stored(places)[0]
    age = _ages(plan.age_unit.unit, plan.age_unit.mode, at, born_at[owner])
    left = np.flatnonzero((at > born_at[owner]) & (age > 0))
    places, owner, age = places[left], owner[left], age[left]
    left = _narrowed(rest, places, chunk.values, lambda a, which: chunk.values(a, births[users][owner[which]]), age)
    left = left[kept[owner[left]]]
    places, owner, age = places[left], owner[left], age[left]

    per = np.bincount(code[kept], minlength=len(cohorts)) if len(users) else np.zeros(0, np.int64)
    full = np.flatnonzero(per)
    emit(len(full), **shown(full), age=0, size=per[full].tolist())
    if len(places):
        width = int(age.max()) + 1
        cell = code[owner] * width + age
        hit, cell = np.unique(cell, return_inverse=True)
        cells = len(hit)
        dense: dict[str, list] = {}
        for i, (_, m) in enumerate(plan.measures):
            if m.kind == "usercount":
                pairs = np.unique(owner * cells + cell)
                dense[f"m{i}_u"] = np.bincount(pairs % cells, minlength=cells).tolist()
            elif m.attr is None:
                dense[f"m{i}_n"] = np.bincount(cell, minlength=cells).tolist()
            else:
                column = chunk.columns[m.attr]
                stored, null = column.stored(places)
                there = ~null
                count = np.bincount(cell[there], minlength=cells)
                for st in m.partial("x"):
                    if st == "s":
                        sums = _exact_sums(column, stored[there], cell[there], cells)
                        dense[f"m{i}_s"] = [x if n else None for x, n in zip(sums, count.tolist(), strict=True)]
                    elif st == "n":
                        dense[f"m{i}_n"] = count.tolist()
                    else:
                        edge = np.full(cells, np.iinfo(np.int64).max if m.kind == "min" else np.iinfo(np.int64).min)
                        (np.minimum if m.kind == "min" else np.maximum).at(edge, cell[there], stored[there])
                        dense[f"m{i}_m"] = [float(x) if n else None for x, n in zip(column.number.real(edge).tolist(), count.tolist(), strict=True)]
        emit(cells, **shown(hit // width), age=(hit % width).tolist(), size=0, **dense)
    emit(1, age=-1, size=0, users_visited=len(births), users_skipped=len(births) - len(users), birth_probes=probes, age_tuples=int(sizes.sum()), values_read=sum(c.reads for c in chunk.columns.values()))
    return out


@dataclass(frozen=True)
class _Slim:
    """What of a plan goes to the executors."""

    table: object
    by: tuple
    measures: tuple
    age_unit: object
    key_kinds: tuple


def partials(plan: CohortPlan, chunks: Chunks, options: ChunkOptions = ChunkOptions()) -> DataFrame:
    """Partial rows of all chunks that aren't pruned: cohort codes, age (0 for sizes, -1 for counters), states."""
    plan = normalise(plan)
    s = plan.table.schema
    if s.user in (*plan.birth_columns, *plan.age_columns):
        raise CohortSemanticError("the chunked executor has no conditions on users")
    wanted = sorted(w for w in {(s.action, plan.action), *_words(plan.birth), *_words(plan.ages)} if w[0] in chunks.strings)
    # one row for each literal of the query
    same = lambda c, v, op: (F.col("column") == c) & (F.col("value") == v if op == "=" else F.col("value") < v)
    look = chunks.dictionary.where(F.col("column").isin(*{c for c, _ in wanted}))
    row = look.agg(*(F.max(F.when(same(c, v, "="), F.col("gid"))).alias(f"i{k}") for k, (c, v) in enumerate(wanted)), *(F.count_if(same(c, v, "<")).alias(f"b{k}") for k, (c, v) in enumerate(wanted))).first()
    known = _Literals({w: row[f"i{k}"] for k, w in enumerate(wanted) if row[f"i{k}"] is not None}, {w: row[f"b{k}"] for k, w in enumerate(wanted)})
    gid = known.ids.get((s.action, plan.action), -2)
    birth_cond, age_cond = (_on_codes(p, chunks, s.time, known, s.user) for p in (plan.birth, plan.ages))
    needed = sorted({s.time, s.action, *plan.birth_columns, *plan.age_columns})
    catalog = chunks.catalog
    if options.prune:
        catalog = catalog.where(possible(conjoin([Cmp("=", Attr(s.action), Lit(gid)), *conjuncts(birth_cond)]), chunks))
    ages = possible(split(age_cond)[0], chunks) if options.prune else F.lit(True)
    texts = [c for c in needed if c in chunks.strings]
    catalog = catalog.select("chunk_id", ages.alias("_ages"), *(F.col("gids")[c].alias(f"g_{chunks.field(c)}") for c in texts))
    source = chunks.chunks.select("chunk_id", "firsts", "counts", *(chunks.field(c) for c in needed)).join(catalog, "chunk_id")
    fields = _fields(plan, chunks)
    arrow = pa.schema([(f.name, {T.LongType: pa.int64(), T.DoubleType: pa.float64()}.get(type(f.dataType), pa.decimal128(38, PLACES))) for f in fields])
    slim = _Slim(replace(plan.table, df=None, birth_index=None), plan.by, plan.measures, plan.age_unit, tuple(f.dataType for f in fields[: len(plan.by)]))
    strings, push = chunks.strings, options.push_birth
    at, numbers = {c: chunks.field(c) for c in needed}, {c: chunks.numbers.get(c) for c in needed}

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            read = {n: batch.column(k) for k, n in enumerate(batch.schema.names)}
            for r in range(batch.num_rows):
                array = lambda column: column[r].values.to_numpy(zero_copy_only=False) if column[r].is_valid else np.zeros(0, np.int64)  # noqa: B023, E731
                columns = {}
                for c, f in at.items():
                    part = read[f]
                    one = {x: part.field(x)[r].as_py() for x in ("low", "nulls", "bits")}
                    gids = array(read[f"g_{f}"]) if c in strings else None
                    columns[c] = PackedColumn(one["bits"], array(part.field("words")), one["low"], one["nulls"], numbers[c], gids)
                blocks = UserBlocks(array(read["firsts"]).astype(np.int64), array(read["counts"]).astype(np.int64))
                got = _partials(slim, _Chunk(blocks, columns, read["_ages"][r].as_py()), gid, birth_cond, age_cond, strings, push)
                yield pa.RecordBatch.from_arrays([pa.array(got[f.name], f.type) for f in arrow], schema=arrow)

    return source.mapInArrow(run, T.StructType(fields))


def counters(plan: CohortPlan, chunks: Chunks, options: ChunkOptions = ChunkOptions()) -> DataFrame:
    """What the executor read: blocks of users visited and skipped, tuples probed for births, tuples looked at after birth, packed values read
    in all, chunks read."""
    rows = partials(plan, chunks, options).where("age = -1")
    return rows.agg(*(F.coalesce(F.sum(c), F.lit(0)).alias(c) for c in COUNTERS), F.count("*").alias("chunks_read"))


def run(plan, chunks: Chunks | None = None, options: ChunkOptions = ChunkOptions()) -> DataFrame:
    plan = normalise(plan)
    chunks = chunks or compress(plan.table)
    rows = partials(plan, chunks, options).where("age >= 0")
    keys = [f"k{i}" for i in range(len(plan.by))]
    merged = {f"m{i}_{st}": F.expr(m.merge(st, f"m{i}_{st}")) for i, (_, m) in enumerate(plan.measures) for st in m.partial("x")}
    cells = rows.groupBy(*keys, "age").agg(F.sum("size").alias("size"), *(e.alias(a) for a, e in merged.items()))
    # the size of a cohort stands in its row of age 0; a window brings it to the others, so nothing is read twice
    whole = Window.partitionBy(F.lit(1), *keys)
    out = cells.withColumn("cohort_size", F.max(F.when(F.col("age") == 0, F.col("size"))).over(whole)).where("age > 0")
    for i, b in enumerate(plan.by):
        if isinstance(b, TimeBin):
            out = out.withColumn(b.name, F.date_add(F.lit("1970-01-01").cast("date"), F.col(f"k{i}").cast("int")))
        elif b in chunks.strings:
            d = chunks.dictionary.where(F.col("column") == b).select(F.col("value").alias(b), F.col("gid").alias(f"_gid{i}"))
            out = out.join(d, F.col(f"k{i}") == F.col(f"_gid{i}"), "left")
        else:
            kind, key = plan.table.df.schema[b].dataType, F.col(f"k{i}")
            if isinstance(kind, T.TimestampType | T.TimestampNTZType):
                back = F.timestamp_micros(key)
            elif isinstance(kind, T.DateType):
                back = F.date_add(F.lit("1970-01-01").cast("date"), (key / 86_400_000_000).cast("int"))
            elif isinstance(kind, T.DecimalType):
                back = key.cast("decimal(38,0)") / 10**kind.scale
            else:
                back = key
            out = out.withColumn(b, back.cast(kind))
    finished = [F.expr(m.finish({st: f"m{i}_{st}" for st in m.partial("x")})).alias(n) for i, (n, m) in enumerate(plan.measures)]
    out = out.select(*plan.cohort_names, F.col("cohort_size").cast("bigint"), F.col("age").cast("int"), *finished)
    return out.select(*plan.columns) if plan.columns else out
