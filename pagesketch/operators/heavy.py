"""Heavy hitters, top lists, popularity, words and word pairs from exact counts and sketches."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from pagesketch.config import PageGeometry
from pagesketch.functions import hashing as H


def hh_exact(stream: DataFrame, k: int) -> DataFrame:
    """(item_key, true_count) of items with at least n/k of the weight."""
    counts = stream.groupBy("item_key").agg(F.sum("weight").cast("bigint").alias("true_count"))
    total = stream.agg(F.sum("weight").alias("n"))
    return counts.crossJoin(F.broadcast(total)).where(F.col("true_count") * k >= F.col("n")).select("item_key", "true_count")


def hh_sketch(estimates: DataFrame, n: int, k: int, mode: str = "strict", eps: float = 0.0) -> DataFrame:
    """Candidates (item_key, est) whose estimate reaches n/k ('strict': every true heavy hitter) or n/k - eps*n ('relaxed')."""
    if mode == "strict":
        return estimates.where(F.col("est") * k >= n)
    return estimates.where(F.col("est").cast("double") >= F.lit(n / k - eps * n))


def majority(stream: DataFrame) -> DataFrame:
    """The item with more than half of the weight, if any."""
    counts = stream.groupBy("item_key").agg(F.sum("weight").cast("bigint").alias("true_count"))
    total = stream.agg(F.sum("weight").alias("n"))
    return counts.crossJoin(F.broadcast(total)).where(F.col("true_count") * 2 > F.col("n")).select("item_key", "true_count")


def hh_page_candidates(stream: DataFrame, geom: PageGeometry, m: int) -> DataFrame:
    """(page, item_key, true_count, place): the m most frequent keys of each page, which is enough since a key has one page."""
    counts = stream.groupBy("item_key").agg(F.sum("weight").cast("bigint").alias("true_count")).withColumn("page", H.page_of(F.col("item_key"), geom))
    place = F.row_number().over(Window.partitionBy("page").orderBy(F.desc("true_count"), "item_key"))
    return counts.withColumn("place", place).where(F.col("place") <= m).select("page", "item_key", "true_count", "place")


def topk(estimates: DataFrame, k: int) -> DataFrame:
    return estimates.orderBy(F.desc("est"), "item_key").limit(k)


def hh_quality(found: DataFrame, exact: DataFrame) -> DataFrame:
    """found, true, hits, precision and recall."""
    both = found.select("item_key").join(exact.select("item_key"), "item_key", "left_semi").agg(F.count("*").alias("hits"))
    out = found.agg(F.count("*").alias("found")).crossJoin(exact.agg(F.count("*").alias("true"))).crossJoin(both)
    return out.select("found", "true", "hits", F.round(F.try_divide("hits", "found"), 6).alias("precision"), F.round(F.try_divide("hits", "true"), 6).alias("recall"))


def words(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(id, pos, word): words between runs of blanks, line feeds and tabs, lower-cased."""
    split = F.split(F.lower(F.col(text_col)), r"[ \n\t]+")
    return docs.select(F.col(id_col).alias("id"), F.posexplode(F.filter(split, lambda w: w != "")).alias("pos", "word"))


def word_stream(tokens: DataFrame) -> DataFrame:
    return tokens.select(H.fingerprint(F.col("word")).alias("item_key"), F.lit(1).cast("bigint").alias("weight"))


def pair_stream(docs: DataFrame, span: int = 2, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(left, right, weight): ordered pairs at most span words apart, made inside each row without a join."""
    split = F.filter(F.split(F.lower(F.col(text_col)), r"[ \n\t]+"), lambda w: w != "")
    rows = docs.select(split.alias("w"))
    pairs = [F.arrays_zip(F.col("w").alias("left"), F.expr(f"slice(w, {d + 1}, greatest(size(w) - {d}, 0))").alias("right")) for d in range(1, span + 1)]
    named = rows.where("size(w) > 1").select(F.explode(F.concat(*(F.transform(p, lambda x: F.struct(x["left"].alias("left"), x["right"].alias("right"))) for p in pairs))).alias("p"))
    return named.where("p.right is not null").select("p.left", "p.right", F.lit(1).cast("bigint").alias("weight"))


def pair_key():
    """Fingerprint of a pair: the length of the left word keeps pairs apart."""
    return H.fingerprint(F.concat(F.length("left").cast("string"), F.lit(":"), F.col("left"), F.lit("|"), F.col("right")))


def pmi(pairs: DataFrame, n_pairs: int, n_words: int, digits: int = 6) -> DataFrame:
    """Adds the pointwise mutual information of (pair_est, left_est, right_est)."""
    ratio = (F.col("pair_est") / F.lit(n_pairs)) / ((F.col("left_est") / F.lit(n_words)) * (F.col("right_est") / F.lit(n_words)))
    return pairs.withColumn("pmi", F.round(F.log2(ratio), digits))
