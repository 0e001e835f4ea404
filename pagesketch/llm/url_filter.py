"""URL rules, carried over redirect and canonical-link aliases by connected components."""

from __future__ import annotations

import re
from collections.abc import Iterator
from dataclasses import dataclass
from html import unescape
from urllib.parse import urljoin

import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from pagesketch.llm.common import cut
from pagesketch.llm.components import components


@dataclass(frozen=True)
class Rule:
    """A verdict for a host with its subdomains and the paths that start with path."""

    verdict: str
    host: str
    path: str

    @property
    def text(self) -> str:
        return self.host + self.path


#: The rules of the production list.
RULES = (
    Rule("block", "net", "/"),
    Rule("allow", "example.net", "/en/"),
    Rule("block", "example.com", "/de/"),
    Rule("allow", "org", "/fr/"),
)

UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
ABSOLUTE, SCHEME = re.compile(r"[A-Za-z][A-Za-z0-9+.\-]*://"), re.compile(r"[A-Za-z][A-Za-z0-9+.\-]*:")
CANONICAL_TAG = r"(?is)<link\b[^>]*\brel\s*=\s*[\"']?canonical\b[^>]*>"
REFRESH_TAG = r"(?is)<meta\b[^>]*\bhttp-equiv\s*=\s*[\"']?refresh\b[^>]*>"
HREF = r"(?is)\bhref\s*=\s*[\"']?([^\"'\s>]+)"
BASE_TAG = r"(?is)<base\b[^>]*\bhref\b[^>]*>"
REFRESH_URL = r"(?is)\burl\s*=\s*[\"']?((?:&#?\w+;|[^\"'\s>;])+)"


def rest_of(url: Column) -> Column:
    """What follows the first ://, empty without one."""
    at = F.instr(url, "://")
    return F.coalesce(F.when(at > 0, F.substring(url, at + 3, F.length(url))), F.lit(""))


def host_of(url: Column) -> Column:
    return F.translate(F.regexp_extract(rest_of(url), r"^([^/?#]*)", 1), UPPER, LOWER)


def path_of(url: Column) -> Column:
    return F.regexp_extract(rest_of(url), r"^[^/?#]*([^?#]*)", 1)


def alias_key(url: Column) -> Column:
    """A url without its scheme and fragment, host lower-cased; null without host."""
    host = host_of(url)
    tail = F.regexp_extract(rest_of(url), r"^[^/?#]*([^#]*)", 1)
    return F.when(host != "", F.concat(host, tail))


def resolved(url: str, target: str) -> str | None:
    """The url that a link on the page of url names; None for one that is no web address. http stands for the scheme of the page."""
    if ABSOLUTE.match(target):
        return target
    if SCHEME.match(target):
        return None
    try:
        return urljoin("http://" + url.partition("://")[2], target)
    except ValueError:
        return None


def _resolve(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """(url, base, target) to (url, target) with target resolved against the base tag, itself resolved against url; entities are decoded first."""
    for batch in batches:
        urls, bases, targets = (batch.column(c).to_pylist() for c in ("url", "base", "target"))
        out = [resolved((resolved(u, unescape(b)) if b else None) or u, unescape(t)) for u, b, t in zip(urls, bases, targets, strict=True)]
        yield pa.RecordBatch.from_arrays([batch.column("url"), pa.array(out, pa.string())], ["url", "target"])


def fits(rule: Rule, host: Column, path: Column) -> Column:
    return ((host == rule.host) | host.endswith("." + rule.host)) & path.startswith(rule.path)


def rule_of(host: Column, path: Column, rules: tuple[Rule, ...] = RULES) -> tuple[Column, Column]:
    """Text and verdict of the longest rule that fits, else null."""
    text = verdict = F.lit(None).cast("string")
    for rule in sorted(rules, key=lambda r: (len(r.text), r.text)):
        text = F.when(fits(rule, host, path), rule.text).otherwise(text)
        verdict = F.when(fits(rule, host, path), rule.verdict).otherwise(verdict)
    return text, verdict


def page_edges(pages: DataFrame, url_col: str = "url", html_col: str = "html") -> DataFrame:
    """Edges between alias keys that all canonical links and redirects of the pages state.

    Relative links are resolved against the url of the page, or its first base tag.
    """
    html = F.coalesce(F.col(html_col), F.lit(""))
    targets = F.concat(
        F.transform(F.regexp_extract_all(html, F.lit(CANONICAL_TAG), 0), lambda tag: F.regexp_extract(tag, HREF, 1)),
        F.transform(F.regexp_extract_all(html, F.lit(REFRESH_TAG), 0), lambda tag: F.regexp_extract(tag, REFRESH_URL, 1)),
    )
    base = F.regexp_extract(F.regexp_extract(html, BASE_TAG, 0), HREF, 1)
    found = pages.where(F.lower(html).contains("canonical") | F.lower(html).contains("refresh"))
    found = found.where(F.col(url_col).contains("://")).select(F.col(url_col).alias("url"), base.alias("base"), F.explode(F.array_distinct(targets)).alias("target"))
    found = found.where("target <> ''").mapInArrow(_resolve, "url string, target string")
    edges = found.select(alias_key(F.col("url")).alias("src"), alias_key(F.col("target")).alias("dst"))
    return edges.where("src is not null and dst is not null and src <> dst")


def judge_urls(
    pages: DataFrame,
    rules: tuple[Rule, ...] = RULES,
    redirects: DataFrame | None = None,
    id_col: str = "page_id",
    url_col: str = "url",
    html_col: str = "html",
) -> DataFrame:
    """page_id, host, path, rule and verdict of every page.

    The longest rule that fits a url decides. Other urls follow their aliases: urls linked
    to them, over any number of steps, by canonical links, refresh tags or rows
    of redirects(src_url, dst_url). If an alias is explicitly allowed they are allowed, else if one is
    blocked they are blocked, else allowed. A null url, or one without ://, has an
    empty host and path, no alias and so is allowed. Repeated rows give repeated results.
    """
    host, path = host_of(F.col(url_col)), path_of(F.col(url_col))
    text, verdict = rule_of(host, path, rules)
    judged = pages.select(
        F.col(id_col).alias("page_id"),
        host.alias("host"),
        path.alias("path"),
        text.alias("rule"),
        verdict.alias("own_verdict"),
        alias_key(F.col(url_col)).alias("node"),
    )
    edges = page_edges(pages, url_col, html_col)
    if redirects is not None:
        edges = edges.unionByName(redirects.select(alias_key(F.col("src_url")).alias("src"), alias_key(F.col("dst_url")).alias("dst")))
    n = pages.count()
    groups = cut(components(edges, rows=n), n)
    as_url = F.concat(F.lit("x://"), F.col("node"))
    _, node_verdict = rule_of(host_of(as_url), path_of(as_url), rules)
    by_group = groups.withColumn("v", node_verdict).groupBy("component").agg(
        F.when(F.max(F.col("v") == "allow"), "allow").when(F.max(F.col("v") == "block"), "block").alias("group_verdict")
    )
    spread = groups.join(by_group, "component").select("node", "group_verdict").where("group_verdict is not null")
    out = judged.join(spread, "node", "left")
    return out.select("page_id", "host", "path", "rule", F.coalesce("own_verdict", "group_verdict", F.lit("allow")).alias("verdict"))
