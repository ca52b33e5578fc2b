"""Point sets: pid LONG, coordinates c0..c{D-1} DOUBLE, any other columns as payload."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from orthant.sources.tables import table


def hash32(c: Column) -> Column:
    """A deterministic spread of ids over 32 bits, the same in other SQL engines."""
    return F.pmod(F.pmod(c, F.lit(2147483648)) * F.lit(2654435761), F.lit(4294967296))


@dataclass(frozen=True)
class PointSet:
    df: DataFrame
    dims: int

    @property
    def coords(self) -> list[str]:
        return [f"c{i}" for i in range(self.dims)]

    @classmethod
    def from_columns(cls, df: DataFrame, pid: str | Column, coords: list[str | Column], **payload: str | Column) -> PointSet:
        col = lambda c: F.col(c) if isinstance(c, str) else c
        own = [col(c).cast("double").alias(f"c{i}") for i, c in enumerate(coords)]
        return cls(df.select(col(pid).cast("long").alias("pid"), *own, *(col(c).alias(n) for n, c in payload.items())), len(coords))

    @classmethod
    def from_array(cls, df: DataFrame, pid: str, array: str, prefix: int, **payload: str | Column) -> PointSet:
        return cls.from_columns(df, pid, [F.get(F.col(array), F.lit(i)) for i in range(prefix)], **payload)

    def positions(self) -> DataFrame:
        """Ids and coordinates only; the scan reads no other column."""
        return self.df.select("pid", *self.coords)

    def where(self, condition: str | Column) -> PointSet:
        return PointSet(self.df.where(condition), self.dims)

    def select_dims(self, dims: list[int]) -> PointSet:
        return PointSet.from_columns(self.df, "pid", [f"c{i}" for i in dims], **{c: c for c in self.df.columns if c not in {"pid", *self.coords}})

    def box_filter(self, lo: list[float], hi: list[float]) -> PointSet:
        """Points inside a closed box; plain ranges on columns, so that they reach the scan."""
        cond = F.lit(True)
        for c, a, b in zip(self.coords, lo, hi, strict=True):
            cond = cond & F.col(c).between(a, b)
        return self.where(cond)

    def bad_rows(self) -> DataFrame:
        """Rows without an id or with a coordinate that is null, NaN or infinite."""
        bad = F.col("pid").isNull()
        for c in self.coords:
            bad = bad | F.col(c).isNull() | F.isnan(c) | (F.abs(F.col(c)) == float("inf"))
        return self.df.where(bad)

    def checked(self, on_bad: str = "error") -> PointSet:
        """on_bad: 'error' raises when a row is bad, 'drop' leaves bad rows out."""
        if on_bad == "drop":
            good = F.col("pid").isNotNull()
            for c in self.coords:
                good = good & F.coalesce(~F.isnan(c) & (F.abs(F.col(c)) != float("inf")), F.lit(False))
            return self.where(good)
        n = self.bad_rows().count()
        if n:
            raise ValueError(f"{n} rows have no id or a coordinate that is no finite number")
        return self

    def scaled(self, how: str = "none") -> PointSet:
        """none, minmax or zscore, by one aggregate."""
        if how == "none":
            return self
        f = {"minmax": lambda c: (F.min(c), F.max(c) - F.min(c)), "zscore": lambda c: (F.avg(c), F.stddev_pop(c))}[how]
        r = self.df.agg(*(x.alias(f"{c}_{n}") for c in self.coords for n, x in zip("ab", f(c), strict=True))).first()
        new = {c: (F.col(c) - r[f"{c}_a"]) / (r[f"{c}_b"] or 1.0) for c in self.coords if r[f"{c}_a"] is not None}
        return PointSet(self.df.withColumns(new), self.dims)

    def sample_queries(self, every: int, remainder: int) -> DataFrame:
        """Queries (qid, coordinates): the points whose id has this remainder."""
        return self.positions().where(F.pmod("pid", F.lit(every)) == remainder).withColumnRenamed("pid", "qid")

    def queries(self) -> DataFrame:
        return self.positions().withColumnRenamed("pid", "qid")


# ---- the workloads' point sets ---------------------------------------------------------------------------------------


def events3(spark: SparkSession, sf_dir: str, **payload: str | Column) -> PointSet:
    days = F.timestamp_diff("MICROSECOND", F.lit("2024-01-01").cast("timestamp_ntz"), F.col("ts")) / F.lit(86400e6)
    k = F.regexp_extract("props", r'"k": *([0-9]+)', 1).cast("double")
    return PointSet.from_columns(table(spark, sf_dir, "events"), "event_id", [days, "value", k], label="event_type", **payload)


def orders3(spark: SparkSession, sf_dir: str) -> PointSet:
    days = F.datediff("o_orderdate", F.lit("1995-01-01").cast("date"))
    return PointSet.from_columns(table(spark, sf_dir, "orders"), "o_orderkey", [F.col("o_totalprice") / 1000, days, "o_custkey"], label="o_orderpriority")


_LINE_KEY = ("l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", "l_quantity", "l_extendedprice", "l_shipdate")


def line3(spark: SparkSession, sf_dir: str) -> PointSet:
    days = F.datediff("l_shipdate", F.lit("1995-01-01").cast("date"))
    return PointSet.from_columns(table(spark, sf_dir, "lineitem"), F.xxhash64(*_LINE_KEY), [F.col("l_extendedprice") / 1000, "l_quantity", days], okey="l_orderkey")


def grid3(spark: SparkSession, sf_dir: str) -> PointSet:
    return PointSet.from_columns(table(spark, sf_dir, "lineitem"), F.xxhash64(*_LINE_KEY), ["l_quantity", F.round(F.col("l_discount") * 100), F.round(F.col("l_tax") * 100)], okey="l_orderkey")


def emb(dims: int):
    def make(spark: SparkSession, sf_dir: str) -> PointSet:
        return PointSet.from_array(table(spark, sf_dir, "embeddings"), "vec_id", "embedding", dims, label="label")

    return make


def doctext10(spark: SparkSession, sf_dir: str) -> PointSet:
    """Ten character statistics of a document; each divided by a literal near its standard deviation."""
    t, n = F.col("text"), F.greatest(F.length("text"), F.lit(1)).cast("double")
    lacks = lambda cls: F.length("text") - F.length(F.regexp_replace(t, cls, ""))
    words, lines = F.split(t, " "), F.split(t, "\n")
    f = [
        n / (n + 2000.0) / 0.2,  # rises with every character, less and less
        F.size(words) / n / 0.05,
        lacks("[éèêàâùçëïôœ]") / n / 0.05,
        lacks("[äöüß]") / n / 0.04,
        lacks("[ñáíóúü]") / n / 0.03,
        lacks("[0-9]") / n / 0.02,
        lacks("[!-/:-@]") / n / 0.05,
        lacks("[A-Z]") / n / 0.1,
        F.size(F.array_distinct(words)) / F.size(words).cast("double") / 0.2,
        F.size(F.array_distinct(lines)) / F.size(lines).cast("double") / 0.2,
    ]
    return PointSet.from_columns(table(spark, sf_dir, "documents"), "doc_id", f, label="lang")


def cust2(spark: SparkSession, sf_dir: str) -> PointSet:
    return PointSet.from_columns(table(spark, sf_dir, "customer"), "c_custkey", ["c_acctbal", "c_nationkey"], label="c_mktsegment")


def part1(spark: SparkSession, sf_dir: str) -> PointSet:
    return PointSet.from_columns(table(spark, sf_dir, "part"), "p_partkey", [F.pmod("p_partkey", F.lit(1000))], target="p_retailprice")


def supp1(spark: SparkSession, sf_dir: str) -> PointSet:
    return PointSet.from_columns(table(spark, sf_dir, "supplier"), "s_suppkey", ["s_acctbal"])
