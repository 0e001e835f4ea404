"""Queries of the relational surface: spreads, ranks, offsets, grouping sets, skewed joins, user functions and sketches of groups, each with its SQL."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql.types import IntegerType, LongType, StructField, StructType

from pagesketch import oracles as O
from pagesketch.config import DELTA, OVERESTIMATE, PageGeometry, SketchConfig
from pagesketch.functions import hashing as H
from pagesketch.operators import heavy, relational
from pagesketch.operators import sketch as S
from pagesketch.queries_apps import PART, WORDS, part_estimates, parts
from pagesketch.queries_core import BASE, HITS, UNIFORM, Case, _hits, case, uniform_stream, with_
from pagesketch.sources.tables import table, uniform_keys
from pagesketch.streaming.ingest import item_stream, windowed_build

QUERIES: dict = {}
SQL: dict[str, str] = {}


def register(name: str, sql: str):
    def put(f):
        QUERIES[name], SQL[name] = f, sql
        return f

    return put


# --- spreads, places and nested text ----------------------------------------------


@register("over_spread", with_(BASE, "SELECT round(stddev_samp(over), 6) AS deviation, round(var_pop(over), 6) AS variance, quantile_disc(over, 0.5)::BIGINT AS median, quantile_disc(over, 0.99)::BIGINT AS p99 FROM pover"))
def over_spread(spark, sf_dir):
    over = F.col("over")
    at = F.percentile_approx(over, [0.5, 0.99], 1_000_000)
    out = case(spark, sf_dir).paged_over().agg(F.round(F.stddev_samp(over), 6).alias("deviation"), F.round(F.var_pop(over), 6).alias("variance"), at.alias("at"))
    return out.select("deviation", "variance", F.col("at")[0].alias("median"), F.col("at")[1].alias("p99"))


@register("topk_offset", with_(PART, "SELECT item_key, est FROM pest ORDER BY est DESC, item_key LIMIT 10 OFFSET 10"))
def topk_offset(spark, sf_dir):
    return part_estimates(parts(spark, sf_dir)).orderBy(F.desc("est"), "item_key").offset(10).limit(10)


@register("runner_up", "SELECT DISTINCT l_returnflag AS grp, nth_value(l_partkey, 2) OVER w AS second FROM (SELECT l_returnflag, l_partkey, count(*) AS n FROM lineitem GROUP BY 1, 2) WINDOW w AS (PARTITION BY l_returnflag ORDER BY n DESC, l_partkey ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING)")
def runner_up(spark, sf_dir):
    """The second most frequent part of each flag; a limit of ranks lets tasks keep two rows a flag before the shuffle."""
    n = table(spark, sf_dir, "lineitem").groupBy(F.col("l_returnflag").alias("grp"), F.col("l_partkey").alias("item_key")).agg(F.count("*").alias("n"))
    w = Window.partitionBy("grp").orderBy(F.desc("n"), "item_key")
    first_two = n.withColumn("place", F.row_number().over(w)).where("place <= 2")
    return first_two.select("grp", F.nth_value("item_key", 2).over(w.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)).alias("second")).distinct()


@register("json_structs", """SELECT '{"k":' || k || ',"n":' || n || '}' AS line FROM (SELECT (props::JSON ->> 'k')::BIGINT AS k, count(*) AS n FROM events GROUP BY 1)""")
def json_structs(spark, sf_dir):
    e = table(spark, sf_dir, "events").select(F.from_json("props", "k bigint").alias("p"))
    return e.groupBy(F.col("p.k").alias("k")).agg(F.count("*").alias("n")).select(F.to_json(F.struct("k", "n")).alias("line"))


@register("estimates_gsets", with_(PART, "SELECT p_brand, p_size, sum(est)::BIGINT AS est FROM pest JOIN part ON p_partkey = item_key GROUP BY GROUPING SETS ((p_brand), (p_size), ())"))
def estimates_gsets(spark, sf_dir):
    named = table(spark, sf_dir, "part").select(F.col("p_partkey").alias("item_key"), "p_brand", "p_size")
    rows = part_estimates(parts(spark, sf_dir)).join(named, "item_key")
    return rows.groupingSets([("p_brand",), ("p_size",), ()], "p_brand", "p_size").agg(F.sum("est").alias("est"))


@register("skewed_join", "SELECT event_id, n FROM events JOIN (SELECT event_type, count(*)::BIGINT AS n FROM events GROUP BY 1) USING (event_type)")
def skewed_join(spark, sf_dir):
    e = table(spark, sf_dir, "events").select("event_id", "event_type")
    return relational.salted_join(e, e.groupBy("event_type").agg(F.count("*").alias("n")), "event_type").select("event_id", "n")


@register("hh_one_pass", f"SELECT t AS word, n FROM (SELECT t, count(*)::BIGINT AS n, sum(count(*)) OVER () AS total FROM ({WORDS}) GROUP BY 1) WHERE n * 100 >= total")
def hh_one_pass(spark, sf_dir):
    """Words with a hundredth of all words: candidates of bounded counters, of which only those are counted."""
    words = heavy.words(table(spark, sf_dir, "documents")).select("word")
    n = words.count()
    found = relational.frequent_candidates(words, "word", 100)
    return words.join(found, "word", "left_semi").groupBy("word").agg(F.count("*").alias("n")).where(F.col("n") * 100 >= n)


@register("w_query_absent", with_(O.sketch_ctes(UNIFORM, queries=f"SELECT {O.fingerprint("'other-1:' || i")} AS item_key FROM (SELECT unnest(range(count(*))) AS i FROM lineitem)"), f"SELECT 'flat' AS method, {HITS} FROM fest UNION ALL SELECT 'paged', {HITS} FROM pest"))
def w_query_absent(spark, sf_dir):
    """As many uniform questions as keys; practically none was inserted."""
    c = Case(uniform_stream(spark, sf_dir))
    asked = uniform_keys(spark, c.n, "other-1").select("item_key")
    flat, paged = S.flat_estimate(c.flat(), asked, c.cfg), S.paged_estimate(c.packed(), asked, c.geom)
    return _hits(flat).withColumn("method", F.lit("flat")).unionByName(_hits(paged).withColumn("method", F.lit("paged")))


# --- user functions ---------------------------------------------------------------


@F.pandas_udf(LongType())
def least_read(cells: pd.Series, places: pd.Series) -> pd.Series:
    """The least of a packed page's counters at the places."""
    return pd.Series([0 if c is None else int(c[p].min()) for c, p in zip(cells, places, strict=True)])


@register("udf_estimate", with_(BASE, "SELECT item_key, est FROM pest"))
def udf_estimate(spark, sf_dir):
    """paged_estimate by an Arrow function over packed pages, as an alternative to the native expression."""
    c = case(spark, sf_dir)
    asked = c.exact.select("item_key", H.page_of(F.col("item_key"), c.geom).alias("page"))
    cols = H.page_columns(F.col("item_key"), F.col("page"), c.geom)
    places = F.array(*((x * c.cfg.depth + i).cast("int") for i, x in enumerate(cols)))
    return asked.join(c.packed(), "page", "left").select("item_key", least_read("cells", places).alias("est"))


@F.udtf(returnType=StructType([StructField("row", IntegerType()), StructField("col", LongType())]))
class CellsOf:
    """A row of a key's cells for each column given."""

    def eval(self, cols):
        yield from enumerate(cols)


@register("udtf_rows", with_(BASE, "SELECT item_key, page, row, col FROM pprobe"))
def udtf_rows(spark, sf_dir):
    """The cells of all keys by a table function in Python, as an alternative to posexplode."""
    c = case(spark, sf_dir)
    spark.udtf.register("cells_of", CellsOf)
    keys = c.exact.select("item_key", H.page_of(F.col("item_key"), c.geom).alias("page"))
    keys.withColumn("cols", F.array(*H.page_columns(F.col("item_key"), F.col("page"), c.geom))).createOrReplaceTempView("located_keys")
    return spark.sql("SELECT item_key, page, row, col FROM located_keys, LATERAL cells_of(cols)")


# --- sketches of groups and days ----------------------------------------------------

GROUP_PAGES = 16
GROUPS = "groups AS (SELECT l_returnflag AS grp, l_partkey AS item_key, count(*) AS c FROM lineitem GROUP BY 1, 2)"
GROUPED = f"{O.sketch_ctes('SELECT l_partkey AS item_key, 1 AS weight FROM lineitem', n=f'max({GROUP_PAGES} * 300)')}, {GROUPS}, gcells AS (SELECT grp, page, row, col, sum(c)::BIGINT AS cnt FROM groups JOIN pprobe USING (item_key) GROUP BY ALL)"


def group_counts(spark, sf_dir) -> tuple[DataFrame, PageGeometry]:
    geom = PageGeometry.of(SketchConfig.from_stream(GROUP_PAGES * 300, OVERESTIMATE, DELTA))
    rows = table(spark, sf_dir, "lineitem").groupBy(F.col("l_returnflag").alias("grp"), F.col("l_partkey").alias("item_key")).agg(F.count("*").alias("c"))
    return rows.withColumn("page", H.page_of(F.col("item_key"), geom)), geom


def group_probes(rows: DataFrame, geom: PageGeometry) -> DataFrame:
    return rows.select("*", F.posexplode(F.array(*H.page_columns(F.col("item_key"), F.col("page"), geom))).alias("row", "col"))


@register("group_cells", with_(GROUPED, "SELECT * FROM gcells"))
def group_cells(spark, sf_dir):
    """A whole sketch for each group, in one aggregation."""
    return group_probes(*group_counts(spark, sf_dir)).groupBy("grp", "page", "row", "col").agg(F.sum("c").alias("cnt"))


@register("group_estimates", with_(GROUPED, "SELECT grp, item_key, min(cnt)::BIGINT AS est FROM groups JOIN pprobe USING (item_key) JOIN gcells USING (grp, page, row, col) GROUP BY 1, 2"))
def group_estimates(spark, sf_dir):
    probes = group_probes(*group_counts(spark, sf_dir))
    return probes.join(group_cells(spark, sf_dir), ["grp", "page", "row", "col"]).groupBy("grp", "item_key").agg(F.min("cnt").alias("est"))


DAILY = O.sketch_ctes("SELECT user_id AS item_key, 1 AS weight FROM events", n="max(20 * 300)")


@register("daily_cells", with_(DAILY, "SELECT epoch_us(time_bucket(INTERVAL 1 DAY, ts))::BIGINT AS start, page, row, col, count(*)::BIGINT AS cnt FROM events JOIN pprobe ON item_key = user_id GROUP BY ALL"))
def daily_cells(spark, sf_dir):
    geom = PageGeometry.of(SketchConfig.from_stream(20 * 300, OVERESTIMATE, DELTA))
    events = table(spark, sf_dir, "events").withColumn("ts", F.col("ts").cast("timestamp"))
    return windowed_build(item_stream(events), geom, "1 day").withColumn("start", F.unix_micros("start"))
