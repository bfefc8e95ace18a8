"""Predicates as a small tree, parsed by Spark and judged three ways: on a file's statistics
(might some row match; must every row match) and on real rows inside a task."""

from __future__ import annotations

import datetime
import hashlib
from dataclasses import dataclass, field
from typing import Any

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

BLOOM_HASHES, BLOOM_BITS = 5, 8192
#: What a tier may look at; "partition" values are exact, so they come first.
TIERS = ("partition", "zone", "presence", "bloom")
_NEGATED = {"=": "<>", "<>": "=", "<": ">=", ">=": "<", ">": "<=", "<=": ">"}
_TURNED = {"=": "=", "<>": "<>", "<": ">", ">": "<", "<=": ">=", ">=": "<="}


def _number(v: Any) -> float | None:
    if isinstance(v, bool):
        return float(v)
    if isinstance(v, datetime.datetime):
        return (v - datetime.datetime(1970, 1, 1)) / datetime.timedelta(microseconds=1)
    if isinstance(v, datetime.date):
        return float((v - datetime.date(1970, 1, 1)).days)
    return None if isinstance(v, str) else float(v)


def text_of(v: Any) -> str:
    """How a value is written in presence lists and bloom filters."""
    return v if isinstance(v, str) else str(int(v)) if isinstance(v, (int, float)) and float(v).is_integer() else str(v)


def bloom_positions(text: str) -> list[int]:
    digest = hashlib.md5(text.encode()).hexdigest()
    return [int(digest[6 * i : 6 * i + 6], 16) % BLOOM_BITS for i in range(BLOOM_HASHES)]


def bloom_positions_column(text: Column) -> Column:
    digest = F.md5(text)
    return F.array(
        *[F.pmod(F.conv(F.substring(digest, 6 * i + 1, 6), 16, 10).cast("int"), F.lit(BLOOM_BITS)) for i in range(BLOOM_HASHES)]
    )


def _stats(name: str) -> Column:
    return F.col("stats")[name]


def _true(c: Column, otherwise: bool) -> Column:
    return F.coalesce(c, F.lit(otherwise))


class Pred:
    def columns(self) -> set[str]:
        raise NotImplementedError

    def might(self, tiers=TIERS) -> Column:
        """False only for files in which no row can match."""
        raise NotImplementedError

    def must(self) -> Column:
        """True only for files in which every row matches."""
        raise NotImplementedError

    def negated(self) -> Pred:
        raise NotImplementedError

    def mask(self, rows: dict[str, np.ndarray]) -> np.ndarray:
        """Which rows match; null never does."""
        raise NotImplementedError

    def pushable(self) -> bool:
        return True

    def sql(self) -> str:
        raise NotImplementedError

    def __and__(self, other: Pred) -> Pred:
        return And((self, other))


def _literal_sql(v: Any) -> str:
    if isinstance(v, str):
        return "'" + v.replace("\\", "\\\\").replace("'", "\\'") + "'"
    if isinstance(v, datetime.datetime):
        return f"TIMESTAMP_NTZ '{v.isoformat(sep=' ')}'"
    if isinstance(v, datetime.date):
        return f"DATE '{v.isoformat()}'"
    return repr(v)


@dataclass(frozen=True)
class Cmp(Pred):
    column: str
    op: str
    value: Any

    def columns(self) -> set[str]:
        return {self.column}

    def _bounds(self) -> tuple[Column, Column, Column]:
        s, n = _stats(self.column), _number(self.value)
        if n is None:
            return s["lo_text"], s["hi_text"], F.lit(self.value)
        return s["lo"], s["hi"], F.lit(n)

    def might(self, tiers=TIERS) -> Column:
        s, (lo, hi, v) = _stats(self.column), self._bounds()
        by_range = {
            "=": (lo <= v) & (v <= hi), "<>": ~((lo == v) & (hi == v)), "<": lo < v, "<=": lo <= v, ">": hi > v, ">=": hi >= v,
        }[self.op]
        out = F.lit(True)
        if "partition" in tiers:
            out = out & (~_true(s["partition"], False) | _true(by_range, True))
        if "zone" in tiers:
            out = out & _true(by_range, True)
        if "presence" in tiers and self.op in ("=", "<>"):
            there = F.array_contains(s["present"], text_of(self.value))
            other = F.size(F.array_remove(s["present"], text_of(self.value))) > 0
            out = out & _true(there if self.op == "=" else other, True)
        if "bloom" in tiers and self.op == "=":
            for bit in bloom_positions(text_of(self.value)):
                word = F.get(s["bloom"], F.lit(bit // 64))
                out = out & _true(F.shiftrightunsigned(word, bit % 64).bitwiseAND(F.lit(1)) == 1, True)
        # a file whose values are all null holds no row that a comparison keeps
        return out & _true(s["nulls"] < F.col("rows"), True)

    def must(self) -> Column:
        s, (lo, hi, v) = _stats(self.column), self._bounds()
        all_in = {
            "=": (lo == v) & (hi == v), "<>": (v < lo) | (v > hi), "<": hi < v, "<=": hi <= v, ">": lo > v, ">=": lo >= v,
        }[self.op]
        return _true(all_in & (s["nulls"] == 0), False)

    def negated(self) -> Pred:
        return Cmp(self.column, _NEGATED[self.op], self.value)

    def mask(self, rows):
        own, n = rows[self.column], _number(self.value)
        v = self.value if n is None else n
        there = _there(own)
        out = np.zeros(len(own), dtype=bool)
        x = own[there]
        out[there] = {
            "=": lambda: x == v, "<>": lambda: x != v, "<": lambda: x < v, "<=": lambda: x <= v, ">": lambda: x > v, ">=": lambda: x >= v,
        }[self.op]()
        return out

    def sql(self) -> str:
        return f"`{self.column}` {self.op} {_literal_sql(self.value)}"


@dataclass(frozen=True)
class In(Pred):
    column: str
    values: tuple
    negative: bool = False

    def columns(self) -> set[str]:
        return {self.column}

    def _each(self) -> list[Cmp]:
        return [Cmp(self.column, "<>" if self.negative else "=", v) for v in self.values]

    def might(self, tiers=TIERS) -> Column:
        if not self.values:
            return F.lit(self.negative)
        if self.negative:
            out = F.lit(True)
            for c in self._each():
                out = out & c.might(tiers)
            return out
        s = _stats(self.column)
        numbers = [_number(v) for v in self.values]
        out = F.lit(True)
        if "zone" in tiers or "partition" in tiers:
            if any(n is None for n in numbers):
                values, lo, hi = F.array(*[F.lit(v) for v in self.values]), s["lo_text"], s["hi_text"]
            else:
                values, lo, hi = F.array(*[F.lit(n) for n in numbers]), s["lo"], s["hi"]
            inside = F.exists(values, lambda v: (v >= lo) & (v <= hi))
            out = out & _true(inside, True) if "zone" in tiers else out & (~_true(s["partition"], False) | _true(inside, True))
        if "presence" in tiers:
            out = out & _true(F.arrays_overlap(s["present"], F.array(*[F.lit(text_of(v)) for v in self.values])), True)
        if "bloom" in tiers and len(self.values) <= 256:
            any_of = F.lit(False)
            for v in self.values:
                any_of = any_of | Cmp(self.column, "=", v).might(("bloom",))
            out = out & any_of
        return out & _true(s["nulls"] < F.col("rows"), True)

    def must(self) -> Column:
        s = _stats(self.column)
        if not self.values:
            return F.lit(False)
        if self.negative:
            out = F.lit(True)
            for c in self._each():
                out = out & c.must()
            return out
        known = F.array(*[F.lit(text_of(v)) for v in self.values])
        return _true((F.size(F.array_except(s["present"], known)) == 0) & (F.size(s["present"]) > 0) & (s["nulls"] == 0), False)

    def negated(self) -> Pred:
        return In(self.column, self.values, not self.negative)

    def mask(self, rows):
        own = rows[self.column]
        there = _there(own)
        values = [v if _number(v) is None else _number(v) for v in self.values]
        out = np.zeros(len(own), dtype=bool)
        found = np.isin(own[there].astype(object) if own.dtype == object else own[there], values)
        out[there] = ~found if self.negative else found
        return out

    def sql(self) -> str:
        return f"`{self.column}` {'NOT ' * self.negative}IN ({', '.join(map(_literal_sql, self.values)) or 'NULL'})"


@dataclass(frozen=True)
class IsNull(Pred):
    column: str
    negative: bool = False

    def columns(self) -> set[str]:
        return {self.column}

    def might(self, tiers=TIERS) -> Column:
        s = _stats(self.column)
        return _true(s["nulls"] < F.col("rows") if self.negative else s["nulls"] > 0, True)

    def must(self) -> Column:
        s = _stats(self.column)
        return _true(s["nulls"] == 0 if self.negative else s["nulls"] == F.col("rows"), False)

    def negated(self) -> Pred:
        return IsNull(self.column, not self.negative)

    def mask(self, rows):
        there = _there(rows[self.column])
        return there if self.negative else ~there

    def sql(self) -> str:
        return f"`{self.column}` IS {'NOT ' * self.negative}NULL"


@dataclass(frozen=True)
class Prefix(Pred):
    column: str
    start: str
    negative: bool = False

    def columns(self) -> set[str]:
        return {self.column}

    def might(self, tiers=TIERS) -> Column:
        s, n = _stats(self.column), len(self.start)
        if self.negative:
            return ~self.negated().must()
        inside = (F.substring(s["lo_text"], 1, n) <= self.start) & (F.substring(s["hi_text"], 1, n) >= self.start)
        return _true(inside, True) & _true(F.exists(s["present"], lambda x: x.startswith(self.start)), True)

    def must(self) -> Column:
        s, n = _stats(self.column), len(self.start)
        if self.negative:
            return ~self.negated().might() & _true(s["nulls"] == 0, False)
        both = (F.substring(s["lo_text"], 1, n) == self.start) & (F.substring(s["hi_text"], 1, n) == self.start)
        return _true(both & (s["nulls"] == 0), False)

    def negated(self) -> Pred:
        return Prefix(self.column, self.start, not self.negative)

    def mask(self, rows):
        own = rows[self.column]
        return np.asarray([x is not None and x.startswith(self.start) != self.negative for x in own], dtype=bool)

    def sql(self) -> str:
        return f"{'NOT ' * self.negative}startswith(`{self.column}`, {_literal_sql(self.start)})"


@dataclass(frozen=True)
class _Many(Pred):
    parts: tuple[Pred, ...]

    def columns(self) -> set[str]:
        return set().union(*(p.columns() for p in self.parts))

    def pushable(self) -> bool:
        return all(p.pushable() for p in self.parts)


@dataclass(frozen=True)
class And(_Many):
    def might(self, tiers=TIERS) -> Column:
        out = F.lit(True)
        for p in self.parts:
            out = out & p.might(tiers)
        return out

    def must(self) -> Column:
        out = F.lit(True)
        for p in self.parts:
            out = out & p.must()
        return out

    def negated(self) -> Pred:
        return Or(tuple(p.negated() for p in self.parts))

    def mask(self, rows):
        return np.logical_and.reduce([p.mask(rows) for p in self.parts])

    def sql(self) -> str:
        return "(" + " AND ".join(p.sql() for p in self.parts) + ")"


@dataclass(frozen=True)
class Or(_Many):
    def might(self, tiers=TIERS) -> Column:
        out = F.lit(False)
        for p in self.parts:
            out = out | p.might(tiers)
        return out

    def must(self) -> Column:
        out = F.lit(False)
        for p in self.parts:
            out = out | p.must()
        return out

    def negated(self) -> Pred:
        return And(tuple(p.negated() for p in self.parts))

    def mask(self, rows):
        return np.logical_or.reduce([p.mask(rows) for p in self.parts])

    def sql(self) -> str:
        return "(" + " OR ".join(p.sql() for p in self.parts) + ")"


@dataclass(frozen=True)
class Opaque(Pred):
    """Anything else: never prunes, is never pushed, and is kept as SQL for the residual."""

    text: str
    names: frozenset = field(default_factory=frozenset)

    def columns(self) -> set[str]:
        return set(self.names)

    def might(self, tiers=TIERS) -> Column:
        return F.lit(True)

    def must(self) -> Column:
        return F.lit(False)

    def negated(self) -> Pred:
        return Opaque(f"NOT ({self.text})", self.names)

    def mask(self, rows):
        raise TypeError(f"{self.text} can't be evaluated inside the search")

    def pushable(self) -> bool:
        return False

    def sql(self) -> str:
        return f"({self.text})"


def _there(values: np.ndarray) -> np.ndarray:
    if values.dtype == object:
        return np.asarray([x is not None for x in values], dtype=bool)
    return ~np.isnan(values)


def row_values(table) -> dict[str, np.ndarray]:
    """Columns of an Arrow table as mask() takes them: numbers and times as doubles with NaN for null, the rest as objects."""
    import pyarrow as pa
    import pyarrow.compute as pc

    out = {}
    for name in table.column_names:
        c = table.column(name)
        if pa.types.is_timestamp(c.type):
            c = pc.cast(pc.cast(c, pa.timestamp("us")), pa.int64())
        elif pa.types.is_date(c.type):
            c = pc.cast(pc.cast(c, pa.date32()), pa.int32())
        elif pa.types.is_boolean(c.type):
            c = pc.cast(c, pa.int8())
        if pa.types.is_integer(c.type) or pa.types.is_floating(c.type) or pa.types.is_decimal(c.type):
            out[name] = pc.cast(c, pa.float64()).to_numpy(zero_copy_only=False) if not c.null_count else np.asarray(
                [np.nan if x is None else float(x) for x in c.to_pylist()]
            )
        elif pa.types.is_string(c.type) or pa.types.is_large_string(c.type):
            out[name] = np.asarray(c.to_pylist(), dtype=object)
    return out


def parse(text: str, schema: T.StructType, spark) -> Pred:
    """Spark parses and resolves the text; the analysed condition is walked."""
    df = spark.createDataFrame([], schema).where(text)
    return from_catalyst(df._jdf.queryExecution().analyzed().condition())


def of_filter(df: DataFrame) -> Pred:
    return from_catalyst(df._jdf.queryExecution().analyzed().condition())


def _value(node) -> Any:
    got = node.eval(None)
    kind = node.dataType().typeName()
    if got is None:
        return None
    if kind == "string":
        return got if isinstance(got, str) else got.toString()
    if kind in ("timestamp_ntz", "timestamp"):
        return datetime.datetime(1970, 1, 1) + datetime.timedelta(microseconds=int(got))
    if kind == "date":
        return datetime.date(1970, 1, 1) + datetime.timedelta(days=int(got))
    if kind.startswith("decimal"):
        return float(got.toString())
    return got


_NUMBERS = {"double", "long", "bigint", "integer", "int", "float", "short", "byte"}


def from_catalyst(node) -> Pred:
    kind = node.getClass().getSimpleName()
    kids = [node.children().apply(i) for i in range(node.children().size())]
    if kind in ("And", "Or"):
        parts: list[Pred] = []
        for p in map(from_catalyst, kids):
            same = isinstance(p, And if kind == "And" else Or)
            parts += p.parts if same else [p]
        return (And if kind == "And" else Or)(tuple(parts))
    if kind == "Not":
        return from_catalyst(kids[0]).negated()
    opaque = Opaque(node.sql(), frozenset(_names(node)))
    ops = {"EqualTo": "=", "LessThan": "<", "LessThanOrEqual": "<=", "GreaterThan": ">", "GreaterThanOrEqual": ">="}
    if kind in ops:
        left, right, op = kids[0], kids[1], ops[kind]
        if left.foldable():
            left, right, op = right, left, _TURNED[op]
        left = _strip(left)
        if left.getClass().getSimpleName() == "AttributeReference" and right.foldable() and (v := _value(right)) is not None:
            return Cmp(left.name(), op, v)
        return opaque
    if kind == "In" and _strip(kids[0]).getClass().getSimpleName() == "AttributeReference" and all(k.foldable() for k in kids[1:]):
        values = tuple(map(_value, kids[1:]))
        return opaque if any(v is None for v in values) else In(_strip(kids[0]).name(), values)
    if kind in ("IsNull", "IsNotNull") and kids[0].getClass().getSimpleName() == "AttributeReference":
        return IsNull(kids[0].name(), kind == "IsNotNull")
    if kind in ("StartsWith", "Like") and kids[0].getClass().getSimpleName() == "AttributeReference" and kids[1].foldable():
        text = _value(kids[1])
        if kind == "StartsWith":
            return Prefix(kids[0].name(), text)
        if text.endswith("%") and not set("%_\\") & set(text[:-1]):
            return Prefix(kids[0].name(), text[:-1])
    return opaque


def _strip(node):
    while node.getClass().getSimpleName() == "Cast" and node.dataType().typeName() in _NUMBERS and node.child().dataType().typeName() in _NUMBERS:
        node = node.child()
    return node


def _names(node) -> set[str]:
    refs = node.references().toSeq()
    return {refs.apply(i).name() for i in range(refs.size())}
