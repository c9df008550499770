"""Names the coordinates of an item stream and checks what users ask of it."""

from __future__ import annotations

from collections.abc import Iterable
from dataclasses import dataclass, field

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: How a null value of a coordinate is written in long form; null is an ordinary value. A text that starts with the mark
#: gets another one in front, so that no value is taken for null.
NULL_MARK = "␀"
#: Columns that results add; coordinates can't have these names.
ADDED = frozenset({"cnt", "share", "mass", "priority", "coord", "value"})


@dataclass(frozen=True)
class StreamSpec:
    """Coordinates, an optional class coordinate, and the columns that identify a row."""

    coords: tuple[str, ...]
    cls: str | None = None
    key: tuple[str, ...] = ()
    types: dict[str, str] = field(default_factory=dict, compare=False)

    @classmethod
    def of(cls, df: DataFrame, coords: Iterable[str], klass: str | None = None, key: Iterable[str] = ()) -> StreamSpec:
        coords, key = tuple(coords), tuple(key)
        kinds = dict(df.dtypes)
        wrong = [c for c in (*coords, *key, *([klass] if klass else ())) if c not in kinds]
        if wrong:
            raise ValueError(f"unknown columns: {wrong}")
        if not coords or len(set(coords)) < len(coords):
            raise ValueError("coordinates must be distinct, one at least")
        unclashed(coords)
        real = [c for c in coords if kinds[c] in ("double", "float")]
        if real:
            raise ValueError(f"bucket real-valued columns first: {real}")
        return cls(coords, klass, key, {c: kinds[c] for c in (*coords, *([klass] if klass else ()))})


def unclashed(names: Iterable[str], added: Iterable[str] = ADDED) -> None:
    clash = sorted(set(names) & set(added))
    if clash:
        raise ValueError(f"rename first, results have columns of these names: {clash}")


def subset(coords: Iterable[str], T: Iterable[str]) -> tuple[str, ...]:
    T = tuple(T)
    if not T or len(set(T)) < len(T) or not set(T) <= set(coords):
        raise ValueError(f"a subset is of distinct known coordinates, one at least: {T}")
    return T


def share_of(gamma: float, name: str = "gamma") -> float:
    if not 0 < gamma <= 1:
        raise ValueError(f"{name} must be in (0, 1]: {gamma}")
    return gamma


def text(c: str | Column) -> Column:
    """A coordinate's value in long form."""
    c = F.col(c) if isinstance(c, str) else c
    v = c.cast("string")
    return F.when(v.isNull(), NULL_MARK).when(v.startswith(NULL_MARK), F.concat(F.lit(NULL_MARK), v)).otherwise(v)


def encode(v: object) -> str:
    if isinstance(v, str) and v.startswith(NULL_MARK):
        return NULL_MARK + v
    return NULL_MARK if v is None else str(v).lower() if isinstance(v, bool) else str(v)


def decoded(c: Column, kind: str) -> Column:
    return F.when(c == NULL_MARK, None).when(c.startswith(NULL_MARK), F.substring(c, 2, 1 << 30)).otherwise(c).cast(kind)


def long_form(df: DataFrame, coords: Iterable[str], keep: Iterable[str] = ()) -> DataFrame:
    """(keep..., coord, value): one row for each coordinate of each item, by Expand inside the scan's stage."""
    coords, keep = list(coords), list(keep)
    ids = [F.col(k).alias(f"__{k}") for k in keep]
    made = df.select(*ids, *(text(c).alias(c) for c in coords)).unpivot([f"__{k}" for k in keep], coords, "coord", "value")
    return made.select(*(F.col(f"__{k}").alias(k) for k in keep), "coord", "value")
