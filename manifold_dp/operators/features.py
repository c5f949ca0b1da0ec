"""Feature rows ``(id, x, label, role)`` from the given tables, unit rows and label codes."""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..functions import norm, unit
from ..sources import POINTS, SMALL, cut, read, require, sized
from .neighbours import lists

BINS = 64


def unit_rows(df: DataFrame, col: str = "x") -> tuple[DataFrame, DataFrame]:
    """Rows at length 1, and the quarantine: null, empty, zero or non-finite vectors, which have no direction."""
    n = norm(F.col(col))
    good = F.coalesce((n > 0) & (n < float("inf")), F.lit(False))
    return df.where(good).withColumn(col, unit(F.col(col))), df.where(~good)


def label_codes(df: DataFrame, col: str, out: str = "label", small: int = SMALL) -> DataFrame:
    """``df`` with dense integer codes of ``col`` from 0 in its order; null stays null.

    Codes come from the distinct values and are joined back. Up to ``SMALL`` values are
    ranked in one task; more are cut into ranges, ranked within each, and moved up by the
    sizes of the ranges before.
    """
    codes = df.where(F.col(col).isNotNull()).select(F.col(col).alias("_value")).distinct()
    if codes.limit(small + 1).count() <= small:
        codes = codes.withColumn("_code", F.row_number().over(Window.orderBy("_value")) - 1)
    else:
        dealt = cut(codes.repartitionByRange("_value").withColumn("_range", F.spark_partition_id()), "codes")
        sizes = dealt.groupBy("_range").agg(F.count(F.lit(1)).alias("_n"), F.min("_value").alias("_least"))
        before = F.coalesce(F.sum("_n").over(Window.orderBy("_least").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))  # one row a range
        place = F.row_number().over(Window.partitionBy("_range").orderBy("_value"))
        codes = dealt.join(F.broadcast(sizes.select("_range", before.alias("_before"))), "_range").select("_value", (F.col("_before") + place - 1).alias("_code"))
    return df.join(sized(codes), F.col(col) == F.col("_value"), "left").withColumn(out, F.col("_code").cast("int")).drop("_value", "_code")


def role_of(id_: Column, seed: int = 42) -> Column:
    """40 % public, 55 % server, 5 % target by hash of the id."""
    h = F.conv(F.substring(F.md5(F.concat_ws(":", F.lit(str(seed)), id_.cast("string"))), 1, 8), 16, 10).cast("long") % 100
    return F.when(h < 40, "public").when(h < 95, "server").otherwise("target")


def raw(spark: SparkSession, sf_dir: str) -> DataFrame:
    e = read(spark, sf_dir, "embeddings")
    rows = e.select(F.col("vec_id").cast("long").alias("id"), F.col("embedding").cast("array<double>").alias("x"), F.col("label").cast("int").alias("label"))
    return unit_rows(rows)[0].withColumn("role", role_of(F.col("id")))


def planted(df: DataFrame, c: float = 1.0) -> DataFrame:
    """Pull each row towards the axis of its label by ``c``, at length 1 again."""
    moved = F.transform("x", lambda z, i: z + F.when(i == F.col("label"), F.lit(float(c))).otherwise(F.lit(0.0)))
    return df.withColumn("x", unit(moved))


def trigrams(df: DataFrame, text: str, key: str = "id", bins: int = BINS) -> DataFrame:
    """``(key, x)``: counts of hashed character trigrams in ``bins`` bins, at length 1.

    Each task counts its own texts, and hashes each distinct trigram of some texts once;
    nothing is shuffled. Texts under three characters have none and are left out. Texts keep
    their case.
    """

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        known: dict[int, int] = {}
        for b in batches:
            for at in range(0, b.num_rows, 256):
                part = b.slice(at, 256)
                chars = [np.frombuffer(z.encode("utf-32-le"), np.uint32).astype(np.int64) for z in part.column(1).to_pylist()]
                grams = np.concatenate([(c[:-2] << 42) | (c[1:-1] << 21) | c[2:] for c in chars])
                found, of = np.unique(grams, return_inverse=True)
                if len(known) > 1 << 20:
                    known.clear()
                for g in found.tolist():
                    if g not in known:
                        text = chr(g >> 42) + chr(g >> 21 & 0x1FFFFF) + chr(g & 0x1FFFFF)
                        known[g] = int(hashlib.md5(text.encode()).hexdigest()[:4], 16) % bins
                bin_ = np.array([known[g] for g in found.tolist()], np.int64)
                doc = np.repeat(np.arange(len(chars)), [len(c) - 2 for c in chars])
                n = np.bincount(doc * bins + bin_[of], minlength=len(chars) * bins).reshape(-1, bins).astype(np.float64)
                yield pa.RecordBatch.from_arrays([part.column(0), lists(n / np.sqrt((n * n).sum(1, keepdims=True)))], [key, "x"])

    rows = df.where(F.char_length(text) >= 3).select(key, text)
    return rows.mapInArrow(count, T.StructType([rows.schema[key], POINTS["x"]]))


def _texts(rows: DataFrame, label: str) -> DataFrame:
    x = trigrams(rows, "text")
    out = label_codes(rows.select("id", F.col(label).alias("_l")), "_l").select("id", "label")
    return x.join(out, "id").withColumn("role", role_of(F.col("id"))).select("id", "x", "label", "role")


def doc_lang(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _texts(read(spark, sf_dir, "documents").select(F.col("doc_id").cast("long").alias("id"), "text", "lang"), "lang")


def doc_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    """As ``doc_lang`` with quality as label: null where a document has none."""
    d = read(spark, sf_dir, "documents").select(F.col("doc_id").cast("long").alias("id"), "text")
    q = read(spark, sf_dir, "labels").select(F.col("doc_id").cast("long").alias("id"), F.col("quality").cast("int").alias("label"))
    return trigrams(d, "text").join(q, "id", "left").withColumn("role", role_of(F.col("id"))).select("id", "x", "label", "role")


def page_lang(spark: SparkSession, sf_dir: str) -> DataFrame:
    p = read(spark, sf_dir, "pages").select(
        F.col("page_id").cast("long").alias("id"),
        F.regexp_extract("html", r'<html[^>]*\slang="([a-z]+)"', 1).alias("lang"),
        F.trim(F.regexp_replace(F.regexp_replace("html", r"(?s)<(script|style|head)[^>]*>.*?</\1>", " "), r"<[^>]*>", " ")).alias("text"),
    )
    return _texts(p, "lang")


def customer_profile(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Standardised order count, spend, discount, balance and recency; label: market segment."""
    orders = read(spark, sf_dir, "orders").select("o_orderkey", "o_custkey", "o_totalprice", "o_orderdate")
    lines = read(spark, sf_dir, "lineitem").groupBy("l_orderkey").agg(F.avg(F.col("l_discount").cast("double")).alias("discount"))
    per = (
        orders.join(lines, F.col("o_orderkey") == F.col("l_orderkey"), "left")
        .groupBy("o_custkey")
        .agg(F.count(F.lit(1)).cast("double").alias("f0"), F.sum(F.col("o_totalprice").cast("double")).alias("f1"), F.avg("discount").alias("f2"), F.max(F.datediff("o_orderdate", F.lit("1990-01-01"))).cast("double").alias("f4"))
    )
    c = read(spark, sf_dir, "customer").select("c_custkey", F.col("c_acctbal").cast("double").alias("f3"), "c_mktsegment")
    rows = c.join(per, F.col("c_custkey") == F.col("o_custkey"), "left").na.fill(0.0, ["f0", "f1", "f2", "f4"])
    cols = [f"f{i}" for i in range(5)]
    stats = rows.agg(*(F.avg(x).alias(f"m{x}") for x in cols), *(F.stddev_pop(x).alias(f"s{x}") for x in cols))
    z = F.array(*((F.col(x) - F.col(f"m{x}")) / F.coalesce(F.nullif(F.col(f"s{x}"), F.lit(0.0)), F.lit(1.0)) for x in cols))
    scaled = rows.crossJoin(F.broadcast(stats)).select(F.col("c_custkey").cast("long").alias("id"), z.alias("x"), "c_mktsegment")
    return unit_rows(label_codes(scaled, "c_mktsegment"))[0].withColumn("role", role_of(F.col("id"))).select("id", "x", "label", "role")


def feature_set(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """``emb_raw``, ``emb_planted``, ``doc_lang``, ``doc_quality``, ``page_lang`` or ``cust_profile``."""
    made = {
        "emb_raw": lambda: raw(spark, sf_dir),
        "emb_planted": lambda: planted(raw(spark, sf_dir)),
        "doc_lang": lambda: doc_lang(spark, sf_dir),
        "doc_quality": lambda: doc_quality(spark, sf_dir),
        "page_lang": lambda: page_lang(spark, sf_dir),
        "cust_profile": lambda: customer_profile(spark, sf_dir),
    }
    return require(made[name]().select("id", "x", "label", "role"), POINTS)


def ml_text_features(spark: SparkSession, sf_dir: str, bins: int = BINS) -> DataFrame:
    """The library's own text pipeline as a variant: words, bigrams, hashed counts, inverse document frequency, unit rows."""
    from pyspark.ml import Pipeline
    from pyspark.ml.feature import IDF, HashingTF, NGram, Normalizer, RegexTokenizer
    from pyspark.ml.functions import vector_to_array

    d = read(spark, sf_dir, "documents").where(F.length("text") > 0).select(F.col("doc_id").cast("long").alias("id"), "text")
    p = Pipeline(stages=[RegexTokenizer(inputCol="text", outputCol="w"), NGram(n=2, inputCol="w", outputCol="g"), HashingTF(numFeatures=bins, inputCol="g", outputCol="t"), IDF(inputCol="t", outputCol="i"), Normalizer(inputCol="i", outputCol="u")])
    return p.fit(d).transform(d).select("id", vector_to_array("u").alias("x"))
