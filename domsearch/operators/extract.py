"""Domains from relations, texts and row slices, in long form: distinct (domain_id, value)."""

from __future__ import annotations

from functools import reduce

import numpy as np
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import minhash
from ..sources.tables import table
from ..store import dealt_numbers, dealt_sets, materialise

MIN_SIZE = 10
SCALARS = ("tinyint", "smallint", "int", "bigint", "float", "double", "string", "boolean", "date", "timestamp", "timestamp_ntz")
COLUMN_TABLES = ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "documents", "pages", "benchmark", "conversations")


def canonical(name: str, kind: str) -> Column:
    """A value as text, the same in every engine: doubles in hundredths, times in ISO form."""
    c = F.col(f"`{name}`")
    if kind in ("double", "float"):
        return F.round(c * 100).cast("bigint").cast("string")
    if kind.startswith("timestamp"):
        return F.date_format(c, "yyyy-MM-dd HH:mm:ss")
    return c.cast("string")


def distinct_entries(entries: DataFrame) -> DataFrame:
    return entries.where("value is not null and value <> ''").distinct()


def from_columns(spark: SparkSession, sf_dir: str, tables: tuple[str, ...] = COLUMN_TABLES, columns: dict[str, list[str]] | None = None) -> DataFrame:
    """Every scalar column as a domain; each table is scanned once."""
    parts = []
    for name in tables:
        df = table(spark, sf_dir, name)
        wanted = [(c, t) for c, t in df.dtypes if t in SCALARS and (columns is None or c in columns.get(name, []))]
        cells = F.array(*(F.struct(F.lit(f"{name}.{c}").alias("domain_id"), canonical(c, t).alias("value")) for c, t in wanted))
        parts.append(df.select(F.explode(cells).alias("e")).select("e.*"))
    return distinct_entries(reduce(DataFrame.unionAll, parts))


def from_tokens(df: DataFrame, id_column: Column, text: Column) -> DataFrame:
    """Token sets: lower-case text cut at white space."""
    return df.select(id_column.alias("domain_id"), F.explode(F.split(F.lower(text), r"\s+")).alias("value"))


def text_entries(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    ids = F.array(F.concat(F.lit("doc:"), F.col("doc_id").cast("string")), F.concat(F.lit("src:"), F.col("source"), F.lit(":"), F.col("lang")), F.concat(F.lit("lang:"), F.col("lang")), F.lit("all:documents"))
    # a document's own tokens are made distinct before they count for its source, its language and the whole
    tokens = docs.select("doc_id", ids.alias("ids"), F.explode(F.array_distinct(F.split(F.lower("text"), r"\s+"))).alias("value"))
    parts = [tokens.select(F.explode("ids").alias("domain_id"), "value")]
    parts.append(from_tokens(table(spark, sf_dir, "conversations"), F.concat(F.lit("conv:"), F.col("conv_id").cast("string")), F.col("text")))
    parts.append(from_tokens(table(spark, sf_dir, "pages"), F.concat(F.lit("page:"), F.col("page_id").cast("string")), F.regexp_replace("html", "<[^>]*>", " ")))
    return distinct_entries(reduce(DataFrame.unionAll, parts))


def from_slices(df: DataFrame, value: Column, labels: list[Column]) -> DataFrame:
    """One row set re-published under several labels, in one scan."""
    return df.select(value.cast("string").alias("value"), F.explode(F.array(*labels)).alias("domain_id")).select("domain_id", "value")


def _by_date(prefix: str, date: str, grains: tuple[str, ...]) -> list[Column]:
    return [F.concat(F.lit(f"{prefix}:{g}:"), F.date_format(F.date_trunc(g, F.col(date).cast("timestamp")), "yyyy-MM-dd")) for g in grains]


def slice_entries(spark: SparkSession, sf_dir: str) -> DataFrame:
    return distinct_entries(slice_rows(spark, sf_dir))


def slice_rows(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Parts shipped and customers ordering by period, parts by customer and by supplier; rows repeat."""
    li = table(spark, sf_dir, "lineitem").select("l_orderkey", "l_partkey", "l_suppkey", "l_shipdate")
    orders = table(spark, sf_dir, "orders").select("o_orderkey", "o_custkey", "o_orderdate")
    shipped = from_slices(li, F.col("l_partkey"), [*_by_date("li.part", "l_shipdate", ("day", "week", "month", "quarter", "year")), F.concat(F.lit("part_by_supp:"), F.col("l_suppkey").cast("string"))])
    ordered = from_slices(orders, F.col("o_custkey"), _by_date("o.cust", "o_orderdate", ("day", "month", "quarter", "year")))
    bought = li.join(orders, li.l_orderkey == orders.o_orderkey).select(F.concat(F.lit("part_by_cust:"), F.col("o_custkey").cast("string")).alias("domain_id"), F.col("l_partkey").cast("string").alias("value"))
    return shipped.unionAll(ordered).unionAll(bought)


def sizes(entries: DataFrame, min_size: int = MIN_SIZE) -> DataFrame:
    return entries.groupBy("domain_id").agg(F.count("*").alias("size")).where(F.col("size") >= min_size)


def with_sizes(entries: DataFrame, min_size: int = MIN_SIZE) -> DataFrame:
    """Entries of the domains that are large enough, with the size."""
    return entries.join(sizes(entries, min_size), "domain_id")


GRAINS = ("day", "week", "month", "quarter", "year")
KINDS = (*(f"li.part:{g}" for g in GRAINS), "part_by_supp", *(f"o.cust:{g}" for g in GRAINS if g != "week"), "part_by_cust")
LINES_A_BUCKET = 100_000  # about 640,000 entries of the slices


def coded_slices(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The rows of ``slice_rows`` as numbers: a domain is 16 times its key or day, plus its kind; ``labelled`` undoes it."""

    def code(key: Column, kind: str) -> Column:
        return key.cast("bigint") * 16 + KINDS.index(kind)

    def days(prefix: str, date: str) -> list[Column]:
        day = F.col(date).cast("date")
        at = {g: day if g == "day" else F.trunc(day, g) for g in GRAINS}
        return [code(F.unix_date(at[g]), f"{prefix}:{g}") for g in GRAINS if f"{prefix}:{g}" in KINDS]

    li = table(spark, sf_dir, "lineitem").select("l_orderkey", "l_partkey", "l_suppkey", "l_shipdate")
    orders = table(spark, sf_dir, "orders").select("o_orderkey", "o_custkey", "o_orderdate")
    rows = [
        li.select(F.explode(F.array(*days("li.part", "l_shipdate"), code(F.col("l_suppkey"), "part_by_supp"))).alias("domain_id"), F.col("l_partkey").alias("value")),
        orders.select(F.explode(F.array(*days("o.cust", "o_orderdate"))).alias("domain_id"), F.col("o_custkey").alias("value")),
        li.join(orders, li.l_orderkey == orders.o_orderkey).select(code(F.col("o_custkey"), "part_by_cust").alias("domain_id"), F.col("l_partkey").alias("value")),
    ]
    return reduce(DataFrame.unionAll, [r.select("domain_id", F.col("value").cast("bigint").alias("value")) for r in rows]).where("domain_id is not null and value is not null")


def stored(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """A corpus written once.  Slices are numbers, dealt out by domain, so that no later step sends their entries again."""
    if name != "slices":
        return materialise(CORPORA[name](spark, sf_dir), "entries")
    return dealt_numbers(coded_slices(spark, sf_dir), buckets(spark, sf_dir), "entries")


def whole(spark: SparkSession, sf_dir: str, name: str, family) -> DataFrame:
    """Domains as whole rows (domain_id, size, sig, steps) by their stored ids, written once: values in order, as differences.

    Values are numbers: those of the slices, and 62 bits of a hash of a text.
    """
    if name == "slices":
        return materialise(dealt_sets(coded_slices(spark, sf_dir), buckets(spark, sf_dir), minhash.portable_sketch(family.m, family.seed), MIN_SIZE), "whole")
    entries = materialise(CORPORA[name](spark, sf_dir), "entries")
    held = entries.groupBy("domain_id").agg(F.array_sort(F.collect_list(value_code(name))).alias("v"))
    signed = minhash.signatures(entries, family).where(F.col("size") >= MIN_SIZE).select("domain_id", "size", F.col("sig").cast("array<int>").alias("sig"))
    steps = F.expr("transform(v, (x, i) -> if(i = 0, x, x - v[i - 1]))").alias("steps")
    return materialise(signed.join(held, "domain_id").select("domain_id", "size", "sig", steps), "whole")


def sketched(spark: SparkSession, sf_dir: str, family) -> DataFrame:
    """(domain_id, size, sig) of the slices by their stored ids: only signatures leave the tasks that hold the sets."""
    return dealt_sets(coded_slices(spark, sf_dir), buckets(spark, sf_dir), minhash.numeric_sketch(family), MIN_SIZE, signs_only=True)


def value_code(name: str) -> Column:
    return F.col("value") if name == "slices" else F.shiftright(F.xxhash64("value"), 2)


def coded_values(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """(code, value) of all distinct values of a corpus."""
    rows = coded_slices(spark, sf_dir) if name == "slices" else CORPORA[name](spark, sf_dir)
    return rows.select("value").distinct().select(value_code(name).alias("code"), F.col("value").cast("string").alias("value"))


def buckets(spark: SparkSession, sf_dir: str) -> int:
    """Of the stored slices."""
    return max(int(spark.conf.get("spark.sql.shuffle.partitions")), table(spark, sf_dir, "lineitem").count() // LINES_A_BUCKET)


def label(code: str, name: str) -> Column:
    """The domain's name of a stored id."""
    if name != "slices":
        return F.col(code)
    kind, key = F.col(code).bitwiseAND(15), F.shiftright(code, 4)
    dated = kind.isin([k for k, x in enumerate(KINDS) if ":" in x])
    return F.concat(F.element_at(F.array(*(F.lit(f"{k}:") for k in KINDS)), kind.cast("int") + 1), F.when(dated, F.date_from_unix_date(key.cast("int")).cast("string")).otherwise(key.cast("string")))


def name_rank(codes: np.ndarray) -> np.ndarray:
    """Positions of distinct stored ids of slices in the order of their names (years of four digits)."""
    kind, key = codes & 15, codes >> 4
    prefix = np.argsort(np.argsort([f"{k}:" for k in KINDS]))[kind]
    dated = np.array([":" in k for k in KINDS])[kind]
    digits = np.abs(key)
    width = np.searchsorted(10 ** np.arange(1, 19), digits, "right") + 1
    text = np.where(dated, key, digits * 10 ** (18 - width))
    rank = np.empty(len(codes), np.int64)
    rank[np.lexsort((width, text, dated | (key >= 0), prefix))] = np.arange(len(codes))
    return rank


def labelled(rows: DataFrame, name: str) -> DataFrame:
    """Rows of a stored corpus with the domains' names, and values as text."""
    return rows.select(*((label(c, name) if c == "domain_id" else F.col(c).cast("string") if c == "value" else F.col(c)).alias(c) for c in rows.columns))


def written(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """(domain_id, value) as text, of a corpus written once."""
    return labelled(stored(spark, sf_dir, name), name)


CORPORA = {"slices": slice_entries, "text": text_entries, "columns": from_columns}
