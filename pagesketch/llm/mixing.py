"""Mixing sources to target weights by hierarchical budgets over a domain-language-source tree.

The token budget flows from the root down; a child's share follows its weight.
What a child cannot supply goes to its siblings in proportion to their weights, and only what all
siblings together cannot supply goes up, to the siblings of the parent. Each leaf then takes
the prefix of its token stream: one seeded permutation of its documents after another.
"""

from __future__ import annotations

import re

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from pagesketch.llm.common import Texts, cut, join_with_hot_keys, over_chunks

LEVELS = ("domain", "lang", "source")
#: Default share of the corpus tokens, in thousandths, and most epochs of a leaf.
BUDGET_PERMILLE = 900
MAX_EPOCHS = 3
SEED = "mix-1"
#: Default weights of the production tree; all others have weight 10.
WEIGHTS = {"domain": {"reference": 30, "web": 50, "forum": 20}, "lang": {"en": 40, "de": 20, "fr": 20, "es": 20}}
OTHER_WEIGHT = 10


NUMBERED = "mixing_n_tokens"


def _count_words(part: pa.RecordBatch) -> pa.RecordBatch:
    _, _, bounds = Texts(part.column("text")).words()
    return pa.RecordBatch.from_arrays([*part.columns[:4], pa.array(np.diff(bounds).astype(np.int64))], ["doc_id", "row_name", "lang", "source", "n_tokens"])


def domain_of(source: Column) -> Column:
    """The production tree's domain of a source: by the last digit of its name."""
    digit = F.regexp_extract(source, r"([0-9])$", 1)
    return F.when(digit.isin("0", "1", "2", "3", "4"), "web").when(digit.isin("5", "6", "7"), "reference").otherwise("forum")


def weight_of(level: str, weights: dict[str, dict[str, int]] = WEIGHTS, other: int = OTHER_WEIGHT) -> Column:
    """Whole-number weight of the node that the column named level holds."""
    out = F.lit(other)
    for name, weight in weights.get(level, {}).items():
        out = F.when(F.col(level) == name, weight).otherwise(out)
    return out.cast("bigint")


def _big(c: Column | str) -> Column:
    return (F.col(c) if isinstance(c, str) else c).cast("decimal(38,0)")


def share_out(children: DataFrame, parent: list[str], name: str) -> DataFrame:
    """Adds budget: the parent's total shared by weight w, no more than capacity cap each.

    Children in the order of cap/w are filled up as long as their capacity is at most
    their share of what is left; the others share the rest by weight, whole tokens, the last gets the remainder.
    """
    of = Window.partitionBy(*parent)
    order = of.orderBy((F.col("cap").cast("double") / F.col("w")).asc(), F.col(name).asc_nulls_first())
    rows = children.withColumn("before", F.sum("cap").over(order) - F.col("cap")).withColumn("weights", F.sum("w").over(of) - F.sum("w").over(order) + F.col("w"))
    rows = rows.withColumn("is_full", _big("cap") * _big("weights") <= _big(F.col("total") - F.col("before")) * _big("w"))
    rows = rows.withColumn("rest", F.col("total") - F.sum(F.when(F.col("is_full"), F.col("cap")).otherwise(0)).over(of))
    rows = rows.withColumn("rest_w", F.sum(F.when(~F.col("is_full"), F.col("w")).otherwise(0)).over(of))
    part = F.when(F.col("is_full"), F.col("cap")).otherwise(F.floor(_big(F.col("rest")) * _big("w") / F.greatest(F.col("rest_w"), F.lit(1))).cast("bigint"))
    rows = rows.withColumn("part", part).withColumn("place", F.row_number().over(order)).withColumn("n", F.count("*").over(of))
    left = F.when((F.col("place") == F.col("n")) & ~F.col("is_full"), F.col("total") - F.sum("part").over(of)).otherwise(0)
    rows = rows.withColumn("budget", F.least(F.col("cap"), F.col("part") + left))
    return rows.drop("before", "weights", "is_full", "rest", "rest_w", "part", "place", "n")


def leaf_budgets(leaves: DataFrame, permille: int = BUDGET_PERMILLE, max_epochs: int = MAX_EPOCHS, weights: dict[str, dict[str, int]] = WEIGHTS, other: int = OTHER_WEIGHT) -> DataFrame:
    """Budgets of the leaves (domain, lang, source, n_docs, n_tokens)."""
    leaves = leaves.withColumn("cap", F.col("n_tokens") * max_epochs)
    total = F.least(F.sum("cap"), F.floor(F.sum("n_tokens") * permille / 1000)).cast("bigint")
    root = leaves.agg(total.alias("total"))
    nodes = leaves.groupBy("domain").agg(F.sum("cap").alias("cap")).withColumn("w", weight_of("domain", weights, other)).crossJoin(root).withColumn("root", F.lit(0))
    up = share_out(nodes, ["root"], "domain").select("domain", F.col("budget").alias("total"))
    nodes = leaves.groupBy("domain", "lang").agg(F.sum("cap").alias("cap")).withColumn("w", weight_of("lang", weights, other)).join(up, "domain")
    up = share_out(nodes, ["domain"], "lang").select("domain", "lang", F.col("budget").alias("total"))
    nodes = leaves.withColumn("w", weight_of("source", weights, other)).join(up, ["domain", "lang"])
    return share_out(nodes, ["domain", "lang"], "source").select(*LEVELS, "n_docs", "n_tokens", "budget")


def _rank(seed: str, epoch: Column) -> Column:
    """A row's place in an epoch's permutation of its leaf."""
    return F.md5(F.concat_ws(":", F.lit(seed), epoch, F.col("row_name")).cast("binary"))


def _edge(sums: DataFrame, place: str) -> DataFrame:
    """Of each leaf's (place, tokens, rest, before), the place at which the running sum of tokens reaches rest, and the sum before it."""
    running = F.sum("tokens").over(Window.partitionBy(*LEVELS).orderBy(place).rowsBetween(Window.unboundedPreceding, 0)) - F.col("tokens")
    return sums.withColumn("before", running + F.col("before")).where((F.col("before") < F.col("rest")) & (F.col("rest") <= F.col("before") + F.col("tokens")))


def leaf_plan(rows: DataFrame, total: int, budgets: DataFrame, seed: str) -> DataFrame:
    """budgets with whole (epochs taken whole), and of the epoch after them cut_rank, its tokens cut_tokens and cut_rows.

    Rows of a lower rank are taken whole, those of cut_rank share cut_tokens. The rank is found by leading digits: two windows of at most 256 places a leaf, then
    one over the 65536th part of a leaf.
    """
    budgets = budgets.withColumn("whole", F.floor(F.col("budget") / F.col("leaf_tokens")).cast("int")).withColumn("rest", F.col("budget") % F.col("leaf_tokens"))
    last = join_with_hot_keys(rows, budgets, list(LEVELS), "n_docs", total).where("rest > 0")
    last = last.select(*LEVELS, "n_tokens", "rest", _rank(seed, F.col("whole") + 1).alias("rank")).withColumn("four", F.substring("rank", 1, 4))
    four = last.groupBy(*LEVELS, "four").agg(F.sum("n_tokens").alias("tokens"), F.first("rest").alias("rest")).withColumn("two", F.substring("four", 1, 2))
    two = four.groupBy(*LEVELS, "two").agg(F.sum("tokens").alias("tokens"), F.first("rest").alias("rest"), F.lit(0).cast("bigint").alias("before"))
    at_two = _edge(two, "two").select(*LEVELS, "two", "before")
    at_four = _edge(four.join(at_two, [*LEVELS, "two"]), "four").select(*LEVELS, "four", "before")
    near = last.join(cut(at_four, 0), [*LEVELS, "four"]).groupBy(*LEVELS, "rank").agg(F.sum("n_tokens").alias("tokens"), F.first("rest").alias("rest"), F.first("before").alias("before"), F.count("*").alias("cut_rows"))
    edge = _edge(near, "rank").select(*LEVELS, F.col("rank").alias("cut_rank"), (F.col("rest") - F.col("before")).alias("cut_tokens"), "cut_rows")
    return cut(budgets.join(edge, list(LEVELS), "left"), 0)


def _taken(rows: DataFrame, plan: DataFrame, total: int, seed: str) -> DataFrame:
    """A row for each chosen epoch of rows (LEVELS, row_name, n_tokens and others), with epoch and taken_tokens."""
    rows = join_with_hot_keys(rows, plan, list(LEVELS), "n_docs", total).where("budget > 0")
    rank = _rank(seed, F.col("whole") + 1)
    last = F.when(rank < F.col("cut_rank"), F.col("n_tokens")).when(rank == F.col("cut_rank"), F.least("n_tokens", F.floor(F.col("cut_tokens") / F.col("cut_rows")).cast("bigint")))
    rows = rows.withColumn("last_tokens", F.coalesce(last, F.lit(0)).cast("bigint"))
    rows = rows.withColumn("epochs", F.col("whole") + F.when(F.col("last_tokens") > 0, 1).otherwise(0)).where("epochs > 0")
    rows = rows.withColumn("epoch", F.explode(F.sequence(F.lit(1), F.col("epochs"))))
    return rows.withColumn("taken_tokens", F.when(F.col("epoch") <= F.col("whole"), F.col("n_tokens")).otherwise(F.col("last_tokens")))


def _named(id_col: str, text_col: str, lang_col: str, source_col: str) -> list[Column]:
    """doc_id, row_name, lang and source of a row; a row without an id is named by its text."""
    name = F.coalesce(F.col(id_col).cast("string"), F.concat(F.lit("?"), F.md5(F.col(text_col).cast("binary"))))
    return [F.col(id_col).cast("bigint").alias("doc_id"), name.alias("row_name"), F.coalesce(F.col(lang_col), F.lit("?")).alias("lang"), F.coalesce(F.col(source_col), F.lit("?")).alias("source")]


class Mix:
    """The selection from docs for target weights over the tree domain, language, source.

    weights holds the whole-number weights of named nodes by level, other_weight that of the rest; domain maps the source column to a domain. A null
    language or source is the node named '?'. Tokens are words; documents without a word supply nothing and
    are not selected. In each epoch a leaf's documents come in the order of md5(seed:epoch:doc_id), where a null id is replaced by a digest of the
    text. The last document of the prefix is taken in part, so that taken_tokens adds up to the leaf's budget; rows with one id in one leaf
    share that part equally and may leave less than one token each.
    """

    def __init__(
        self,
        docs: DataFrame,
        permille: int = BUDGET_PERMILLE,
        max_epochs: int = MAX_EPOCHS,
        seed: str = SEED,
        id_col: str = "doc_id",
        text_col: str = "text",
        lang_col: str = "lang",
        source_col: str = "source",
        weights: dict[str, dict[str, int]] = WEIGHTS,
        other_weight: int = OTHER_WEIGHT,
        domain=domain_of,
    ):
        self.docs, self.seed, self.text_col, self.domain = docs, seed, text_col, domain
        self.names = _named(id_col, text_col, lang_col, source_col)
        rows = docs.select(*self.names, F.col(text_col).alias("text"))
        rows = rows.mapInArrow(over_chunks(_count_words), "doc_id bigint, row_name string, lang string, source string, n_tokens bigint").where("n_tokens > 0")
        self.rows = cut(rows.select("doc_id", "row_name", domain(F.col("source")).alias("domain"), "lang", "source", "n_tokens"))
        leaves = self.rows.groupBy(*LEVELS).agg(F.count("*").alias("n_docs"), F.sum("n_tokens").alias("n_tokens"))
        budgets = cut(leaf_budgets(leaves, permille, max_epochs, weights, other_weight).withColumnRenamed("n_tokens", "leaf_tokens"), 0)
        self.total = budgets.agg(F.coalesce(F.sum("n_docs"), F.lit(0))).first()[0]
        self.plan = leaf_plan(self.rows, self.total, budgets, seed)

    def selection(self) -> DataFrame:
        """(doc_id, domain, lang, source, epoch, n_tokens, taken_tokens), a row for each chosen epoch of a document."""
        return _taken(self.rows, self.plan, self.total, self.seed).select("doc_id", *LEVELS, "epoch", "n_tokens", "taken_tokens")

    def texts(self) -> DataFrame:
        """The rows of docs for each chosen epoch, with all their columns and the text cut after the taken tokens. No text is shuffled.

        A column n_chars, if there is one, follows the cut text.
        """
        columns, text_col = self.docs.columns, self.text_col
        rows = self.docs.select(F.struct("*").alias("own"), *self.names)
        rows = rows.select("own", "row_name", self.domain(F.col("source")).alias("domain"), "lang", "source", _n_words(F.col(f"own.{text_col}")).alias("n_tokens")).where("n_tokens > 0")
        rows = _taken(rows, self.plan, self.total, self.seed).select("own.*", F.when(F.col("taken_tokens") < F.col("n_tokens"), F.col("taken_tokens")).alias(NUMBERED))

        def run(batches):
            for batch in batches:
                texts, at = batch.column(text_col), batch.column(NUMBERED)
                if at.null_count < len(at):
                    pairs = zip(texts.to_pylist(), at.to_pylist(), strict=True)
                    texts = pa.array([t if k is None else first_words(t, k) for t, k in pairs], texts.type)
                yield batch.set_column(batch.schema.get_field_index(text_col), text_col, texts)

        rows = rows.mapInArrow(run, rows.schema)
        if "n_chars" in columns:
            rows = rows.withColumn("n_chars", F.when(F.col(NUMBERED).isNotNull(), F.length(text_col)).otherwise(F.col("n_chars")).cast(self.docs.schema["n_chars"].dataType))
        return rows.select(*columns)


WORD = r"[^\x20\x09-\x0D]+"


def _n_words(text: Column) -> Column:
    return F.coalesce(F.regexp_count(text, F.lit(WORD)), F.lit(0)).cast("bigint")


def first_words(text: str, k: int) -> str:
    """A text up to the end of its k-th word."""
    end = 0
    for _, found in zip(range(k), re.finditer(WORD, text)):
        end = found.end()
    return text[:end]


def mix(docs: DataFrame, permille: int = BUDGET_PERMILLE, max_epochs: int = MAX_EPOCHS, **more) -> DataFrame:
    """Mix(...).selection()."""
    return Mix(docs, permille, max_epochs, **more).selection()
