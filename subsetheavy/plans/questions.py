"""Questions in SQL text over a fitted model: whether a joint value is heavy, and which are.

register(spark, model) makes, under a name of the user's choice,
  * a view <name> of the model: (coord, value, cnt, share, by_class array<double>, prior array<double>);
  * <name>_share(coords, vals): the model's share of a joint value (null where a value is no survivor), a SQL function over
    the view: the model, whose size is bounded, is gathered once and looked up in the rows' own stage;
  * <name>_verdict(coords, vals, cut): whether that share reaches the cut.
Besides, for every session: the table functions heavy_values(TABLE(view), coords, cut), which lists heavy joint values, and
subcubes(coords, k), which lists the subsets of k coordinates. A model has at most coordinates / lam rows whatever the
stream, so the one task of heavy_values holds it.
"""

import re
from itertools import combinations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.functions import pandas_udf, udtf
from pyspark.sql.types import DoubleType, LongType

from ..operators.models import Model, prior_array
from ..spec import NULL_MARK


@udtf(returnType="vals array<string>, mass double")
class HeavyValues:
    """Grows prefixes over a model's rows by falling share; coords is a comma-separated list."""

    def __init__(self):
        self.by: dict[str, list] = {}
        self.prior, self.coords, self.cut = [1.0], None, 0.0

    def eval(self, row, coords: str, cut: float):
        self.coords, self.cut = [c.strip() for c in coords.split(",")], float(cut)
        if row["prior"]:
            self.prior = list(row["prior"])
        self.by.setdefault(row["coord"], []).append((row["value"], list(row["by_class"])))

    def terminate(self):
        if not self.coords or len(set(self.coords)) < len(self.coords):
            return
        have = [((), self.prior)]
        for c in self.coords:
            # the largest share within a class bounds what a value can leave of a prefix
            values = sorted(((max(s), v, s) for v, s in self.by.get(c, [])), key=lambda x: -x[0])
            grown = []
            for vals, q in have:
                whole = sum(q)
                for top, v, s in values:
                    if whole * top < self.cut:
                        break
                    new = [a * b for a, b in zip(q, s, strict=True)]
                    if sum(new) >= self.cut:
                        grown.append(((*vals, v), new))
            have = grown
        for vals, q in have:
            yield [_plain(v) for v in vals], float(sum(q))


def _plain(v: str) -> str | None:
    return None if v == NULL_MARK else v[1:] if v.startswith(NULL_MARK) else v


@udtf(returnType="subcube_id bigint, pos int, coord string")
class Subcubes:
    """Every subset of k coordinates, in order, a row for each place."""

    def eval(self, coords: str, k: int):
        names = [c.strip() for c in coords.split(",")]
        for i, T in enumerate(combinations(names, k)):
            for pos, c in enumerate(T, 1):
                yield i, pos, c


@pandas_udf(LongType())
def band(share: pd.Series) -> pd.Series:
    """The power of two that a share lies under."""
    return np.floor(-np.log2(share)).astype("int64")


@pandas_udf(DoubleType())
def top_share(counts: pd.Series) -> float:
    """The largest count over their sum."""
    return float(counts.max() / counts.sum()) if len(counts) else 0.0


def view_of(model: Model) -> DataFrame:
    """The model as one table for SQL: shares within classes, and the classes' shares, as arrays (a product has one)."""
    by = F.col("cond") if model.mixture else F.array("share")
    return model.table.select("coord", "value", "cnt", "share", by.alias("by_class"), (prior_array(model) if model.mixture else F.array(F.lit(1.0))).alias("prior"))


def register(spark: SparkSession, model: Model, name: str = "model") -> None:
    """Make the view and the functions of the module's docstring; the names replace those of an earlier model."""
    if not re.fullmatch(r"[a-z][a-z0-9_]*", name):
        raise ValueError(f"a lower-case name: {name}")
    view_of(model).createOrReplaceTempView(name)
    spark.udtf.register("heavy_values", HeavyValues)
    spark.udtf.register("subcubes", Subcubes)
    mark = f"'{NULL_MARK}'"
    written = f"coalesce(CASE WHEN startswith(v, {mark}) THEN concat({mark}, v) ELSE v END, {mark})"
    # the model as one map, read once for a query: its rows are bounded; a fold over the coordinates, a sum over classes
    spark.sql(f"""CREATE OR REPLACE TEMPORARY FUNCTION {name}_fold(m MAP<STRING, ARRAY<DOUBLE>>, prior ARRAY<DOUBLE>, cs ARRAY<STRING>, vs ARRAY<STRING>) RETURNS DOUBLE RETURN
      CASE WHEN size(cs) = size(vs) THEN aggregate(aggregate(zip_with(cs, vs, (c, v) -> m[concat(c, '=', {written})]), prior, (acc, s) -> zip_with(acc, s, (a, b) -> a * b)), 0D, (acc, x) -> acc + x) END""")
    spark.sql(f"""CREATE OR REPLACE TEMPORARY FUNCTION {name}_share(cs ARRAY<STRING>, vs ARRAY<STRING>) RETURNS DOUBLE RETURN
      {name}_fold((SELECT map_from_entries(collect_list(struct(concat(coord, '=', value), by_class))) FROM {name}), (SELECT any_value(prior) FROM {name}), cs, vs)""")
    spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {name}_verdict(cs ARRAY<STRING>, vs ARRAY<STRING>, line DOUBLE) RETURNS BOOLEAN RETURN coalesce({name}_share(cs, vs) >= line, FALSE)")


def heavy_sql(spark: SparkSession, T, cut: float, name: str = "model") -> DataFrame:
    """(T..., mass) by the SQL text a user would write."""
    cols = ", ".join(f"vals[{i}] AS `{c}`" for i, c in enumerate(T))
    return spark.sql(f"SELECT {cols}, mass FROM heavy_values(TABLE({name}) WITH SINGLE PARTITION, '{','.join(T)}', {cut!r}D)")
