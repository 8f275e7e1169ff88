"""Baskets (tid, items): items is a sorted array of distinct strings without nulls."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .tables import read


def from_rows(rows: DataFrame, key: Column, item: Column) -> DataFrame:
    """Rows (key, item): null items are dropped; a key with no other item has no basket."""
    return rows.select(key.alias("tid"), item.cast("string").alias("item")).where("item is not null").groupBy("tid").agg(F.array_sort(F.collect_set("item")).alias("items"))


def from_columns(rows: DataFrame, key: Column, columns: list[str]) -> DataFrame:
    """Attributes of a row as items `column=value`; null attributes are dropped."""
    pairs = F.array_compact(F.array(*(F.when(F.col(c).isNotNull(), F.concat(F.lit(f"{c}="), F.col(c).cast("string"))) for c in columns)))
    return rows.select(key.alias("tid"), F.array_sort(F.array_distinct(pairs)).alias("items"))


def from_array(rows: DataFrame, key: Column, values: Column) -> DataFrame:
    return rows.select(key.alias("tid"), F.array_sort(F.array_distinct(F.array_compact(F.coalesce(values, F.array().cast("array<string>"))))).alias("items"))


def from_text(rows: DataFrame, key: Column, text: Column, unit: str = "words", stop: tuple[str, ...] = (), stem: Callable[[Column], Column] | None = None) -> DataFrame:
    """Distinct lower-cased letter runs (`words`), white-space pieces (`pieces`) or non-empty lines (`lines`) of a text, less `stop`, then cut by `stem`."""
    whole = F.coalesce(text, F.lit(""))
    if unit == "words":
        parts = F.regexp_extract_all(F.lower(whole), F.lit(r"\p{L}+"), F.lit(0))
    else:
        parts = F.filter(F.split(whole, r"\n" if unit == "lines" else r"\s+"), lambda x: F.trim(x) != "")
    parts = F.array_except(parts, F.array(*map(F.lit, stop))) if stop else F.array_distinct(parts)
    parts = F.array_distinct(F.transform(parts, stem)) if stem else parts
    return rows.select(key.alias("tid"), F.array_sort(parts).alias("items"))


#: Words that carry little meaning, and endings that are cut from English words of five letters and more.
STOP_WORDS = tuple("a an and are as at be but by for from has have he her his i if in into is it its not of on or our she so such that the their then there these they this to was we were which will with you your".split())
ENDINGS = "(ingly|edly|ations|ation|ings|ing|ies|ied|ness|ments|ment|ers|er|ed|ly|es|s)$"


def stemmed(word: Column) -> Column:
    """A word without one common ending, if three letters stay."""
    cut = F.regexp_replace(word, ENDINGS, "")
    return F.when((F.length(word) >= 5) & (F.length(cut) >= 3), cut).otherwise(word)


def from_vector(rows: DataFrame, key: Column, vector: Column, threshold: float | None = None, top: int | None = None) -> DataFrame:
    """Dimensions above a threshold, or the `top` largest ones, as items `d<i>`."""
    values = F.transform(vector, lambda v, i: F.struct(v.alias("v"), i.alias("i")))
    kept = F.slice(F.reverse(F.array_sort(values)), 1, top) if top else F.filter(values, lambda s: s["v"] > threshold)
    return rows.select(key.alias("tid"), F.array_sort(F.transform(kept, lambda s: F.concat(F.lit("d"), s["i"].cast("string")))).alias("items"))


def from_json(rows: DataFrame, key: Column, document: Column, path: str) -> DataFrame:
    return from_rows(rows, key, F.concat(F.lit(path.removeprefix("$.") + "="), F.get_json_object(document, path)))


def limited(baskets: DataFrame, min_df: int = 1, max_vocab: int | None = None) -> DataFrame:
    """Baskets over the items in min_df baskets or more, of those the max_vocab commonest (ties by item).

    A basket that loses all its items stays, empty, and so counts in m.
    """
    if min_df <= 1 and max_vocab is None:
        return baskets
    long = baskets.select("tid", F.explode_outer("items").alias("item"))
    counts = long.where("item is not null").groupBy("item").agg(F.count("*").alias("n")).where(F.col("n") >= min_df)
    if max_vocab is not None:
        counts = counts.orderBy(F.desc("n"), "item").limit(max_vocab)
    kept = long.join(counts.select("item", F.col("item").alias("kept")), "item", "left")
    return kept.groupBy("tid").agg(F.array_sort(F.collect_set("kept")).alias("items"))


def _geo(spark: SparkSession, d: str) -> DataFrame:
    nations = read(spark, d, "supplier").join(read(spark, d, "nation"), F.col("s_nationkey") == F.col("n_nationkey")).select("s_suppkey", "s_nationkey", "n_regionkey")
    return read(spark, d, "lineitem").select("l_orderkey", "l_partkey", "l_suppkey").join(nations, F.col("l_suppkey") == F.col("s_suppkey"))


def _n(column: str) -> Column:
    return F.concat(F.lit("n"), F.col(column).cast("string"))


def _r(column: str) -> Column:
    return F.concat(F.lit("r"), F.col(column).cast("string"))


def _lines_of_parts(spark: SparkSession, d: str) -> DataFrame:
    return read(spark, d, "lineitem").select("l_orderkey", "l_partkey").join(read(spark, d, "part").select("p_partkey", "p_brand", "p_name"), F.col("l_partkey") == F.col("p_partkey"))


def _order_geo(spark, d):
    both = _geo(spark, d).select("l_orderkey", F.explode(F.array(_n("s_nationkey"), _r("n_regionkey"))).alias("item"))
    return from_rows(both, F.col("l_orderkey"), F.col("item"))


def _part_custnations(spark, d):
    buyers = read(spark, d, "orders").join(read(spark, d, "customer"), F.col("o_custkey") == F.col("c_custkey")).select("o_orderkey", "c_nationkey")
    lines = read(spark, d, "lineitem").select("l_orderkey", "l_partkey").join(buyers, F.col("l_orderkey") == F.col("o_orderkey"))
    return from_rows(lines, F.col("l_partkey"), _n("c_nationkey"))


def _cust_brands(spark, d):
    lines = _lines_of_parts(spark, d).join(read(spark, d, "orders").select("o_orderkey", "o_custkey"), F.col("l_orderkey") == F.col("o_orderkey"))
    return from_rows(lines, F.col("o_custkey"), F.col("p_brand"))


def _part_attrs(spark, d):
    part = read(spark, d, "part")
    return from_array(part, F.col("p_partkey"), F.concat(F.split("p_name", " "), F.array("p_brand", "p_type")))


def _line_attrs(spark, d):
    line = read(spark, d, "lineitem").withColumn("row", F.monotonically_increasing_id())
    return from_columns(line, F.col("row"), ["l_returnflag", "l_linestatus", "l_discount", "l_tax", "l_linenumber"])


def _page_words(spark, d):
    return from_text(read(spark, d, "pages"), F.col("page_id"), F.regexp_replace("html", "<[^>]*>", " "))


def _page_tags(spark, d):
    tags = F.regexp_extract_all(F.col("html"), F.lit(r"<([a-z][a-z0-9]*)"), F.lit(1))
    return from_array(read(spark, d, "pages"), F.col("page_id"), tags)


#: name -> function of (spark, sf_dir)
SOURCES: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    "order_geo": _order_geo,
    "order_regions": lambda s, d: from_rows(_geo(s, d), F.col("l_orderkey"), _r("n_regionkey")),
    "order_brands": lambda s, d: from_rows(_lines_of_parts(s, d), F.col("l_orderkey"), F.col("p_brand")),
    "order_tokens": lambda s, d: from_rows(_lines_of_parts(s, d).select("l_orderkey", F.explode(F.split("p_name", " ")).alias("w")), F.col("l_orderkey"), F.col("w")),
    "order_parts": lambda s, d: from_rows(read(s, d, "lineitem"), F.col("l_orderkey"), F.col("l_partkey")),
    "part_suppnations": lambda s, d: from_rows(_geo(s, d), F.col("l_partkey"), _n("s_nationkey")),
    "part_custnations": _part_custnations,
    "cust_brands": _cust_brands,
    "part_attrs": _part_attrs,
    "line_attrs": _line_attrs,
    "doc_words_en": lambda s, d: from_text(read(s, d, "documents").where("lang = 'en'"), F.col("doc_id"), F.col("text")),
    "doc_stems_en": lambda s, d: from_text(read(s, d, "documents").where("lang = 'en'"), F.col("doc_id"), F.col("text"), stop=STOP_WORDS, stem=stemmed),
    "doc_words": lambda s, d: from_text(read(s, d, "documents"), F.col("doc_id"), F.col("text")),
    "conv_words": lambda s, d: from_text(read(s, d, "conversations"), F.concat_ws("/", "conv_id", "turn"), F.col("text")),
    "doc_lines": lambda s, d: from_text(read(s, d, "documents"), F.col("doc_id"), F.col("text"), "lines"),
    "page_words": _page_words,
    "page_tags": _page_tags,
    "bench_words": lambda s, d: from_text(read(s, d, "benchmark"), F.col("item_id"), F.col("text")),
    "userday_events": lambda s, d: from_rows(read(s, d, "events"), F.concat_ws("@", F.col("user_id"), F.date_format("ts", "yyyy-MM-dd")), F.col("event_type")),
    "user_props": lambda s, d: from_json(read(s, d, "events"), F.col("user_id"), F.col("props"), "$.k"),
    "vec_dims": lambda s, d: from_vector(read(s, d, "embeddings"), F.col("vec_id"), F.col("embedding"), threshold=0.15),
}


def source(spark: SparkSession, sf_dir: str, name: str, include_empty: bool = False, min_df: int = 1, max_vocab: int | None = None) -> DataFrame:
    """A basket source by name.  Empty baskets are left out unless asked for; those that only min_df or max_vocab empty stay and count in m."""
    found = SOURCES[name](spark, sf_dir)
    return limited(found if include_empty else found.where(F.size("items") > 0), min_df, max_vocab)
