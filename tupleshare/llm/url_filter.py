"""URL filtering: pattern rules indexed by their rarest literal token."""

from __future__ import annotations

import re
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import ascii_lower

#: Rules are broadcast; more than this is refused rather than sent to every executor.
MAX_RULES = 200_000


@dataclass(frozen=True)
class Rule:
    """A rule on `host` and all its subdomains and paths that start with `path` (form "host"), or a regular
    expression searched in the A-Z lower-cased url (form "pattern"). `literals` are tokens, runs of a-z and 0-9,
    that stand whole in every url the rule matches."""

    name: str
    verdict: str
    form: str
    regex: str
    literals: tuple[str, ...]


def host_rule(verdict: str, name: str) -> Rule:
    """From `example.org/es/`. The path's last token may go on in the url, so it is no literal unless `/` ends it."""
    host, _, path = name.partition("/")
    path = "/" + path
    whole = path if path.endswith("/") else path[: path.rfind("/") + 1]
    literals = re.findall(r"[a-z0-9]+", host) + re.findall(r"[a-z0-9]+", whole.lower())
    return Rule(name, verdict, "host", rf"^(?:[^/]*\.)?{re.escape(host)}{re.escape(path)}", tuple(dict.fromkeys(literals)))


def pattern_rule(verdict: str, regex: str, *literals: str) -> Rule:
    return Rule(regex, verdict, "pattern", regex, literals)


HOST_RULES = [host_rule("allow", "org/"), host_rule("block", "example.org/es/"), host_rule("block", "example.org/en/1"), host_rule("allow", "com/fr/"), host_rule("block", "com/de/")]
PATTERN_RULES = [
    pattern_rule("block", r"[/.]casino[/.]", "casino"),
    pattern_rule("block", r"[/.]torrent[/.]", "torrent"),
    pattern_rule("block", r"[/.]porn[/.]", "porn"),
    pattern_rule("block", r"/wp-admin(?:[/?#]|$)", "wp", "admin"),
    pattern_rule("block", r"/login(?:[/?#.]|$)", "login"),
    pattern_rule("block", r"/checkout/cart(?:[/?#]|$)", "checkout", "cart"),
    pattern_rule("block", r"^[a-z]+://ads?\.[^/?#]*\.example\.", "example"),
    pattern_rule("block", r"[?&]page=[5-9][0-9][0-9]", "page"),
]
URL_FORM = r"(?s)^.*?://([^/?#]*)([^?#]*)"


def host_of(url: Column) -> Column:
    return F.coalesce(ascii_lower(F.regexp_extract(url, URL_FORM, 1)), F.lit(""))


def path_of(url: Column) -> Column:
    return F.coalesce(F.regexp_extract(url, URL_FORM, 2), F.lit(""))


def judge_urls(pages: DataFrame, rules: list[Rule], id_col: str = "page_id", url_col: str = "url", default: str = "allow") -> DataFrame:
    """One row per input row: id, host, path, rule, verdict.

    The rarest literal of each rule over all urls is its key in the index. A url's tokens fetch the rules under them,
    and only these run their expression; a rule without literals has the empty token, which every url has. Host rules win over patterns, then the longest rule, then the greater name.
    `rule` is null unless a host rule decides; without any match the verdict is `default`. A null url, or one without
    `://`, has empty host and path; patterns still see it. Repeated rows are judged one by one, columns beside id and
    url are not read, an empty table gives an empty result.
    """
    if len(rules) > MAX_RULES:
        raise ValueError(f"{len(rules)} rules; the index is broadcast and may hold {MAX_RULES}")
    spark = pages.sparkSession
    low = ascii_lower(F.coalesce(F.col("url"), F.lit("")))
    literals = sorted({t for r in rules for t in r.literals})
    known = F.array(*map(F.lit, literals)) if literals else F.array().cast("array<string>")
    always = F.array(F.lit("")) if any(not r.literals for r in rules) else F.array().cast("array<string>")
    tokens = F.array_union(always, F.array_intersect(known, F.split(low, "[^a-z0-9]+")))
    urls = pages.select(F.col(id_col).alias("id"), F.col(url_col).cast("string").alias("url")).withColumn("tokens", tokens)

    counts = urls.select(F.explode("tokens").alias("token")).groupBy("token").agg(F.count("*").alias("n"))
    schema = T.StructType([T.StructField(k, T.StringType()) for k in ("name", "verdict", "form", "regex")] + [T.StructField("literals", T.ArrayType(T.StringType()))])
    listed = spark.createDataFrame([(r.name, r.verdict, r.form, r.regex, list(r.literals)) for r in rules], schema)
    index = (
        listed.withColumn("token", F.explode(F.when(F.size("literals") > 0, F.col("literals")).otherwise(F.array(F.lit("")))))
        .join(counts, "token", "left")
        .groupBy("name", "verdict", "form", "regex")
        .agg(F.min(F.struct(F.coalesce("n", F.lit(0)).alias("n"), "token"))["token"].alias("token"))
    )

    numbered = urls.select(F.monotonically_increasing_id().alias("row"), "id", host_of(F.col("url")).alias("host"), path_of(F.col("url")).alias("path"), low.alias("low"), "tokens")
    probes = numbered.select("row", "id", "host", "path", "low", F.explode_outer("tokens").alias("token"))
    fits = F.when(F.col("form") == "host", F.expr("concat(host, path) rlike regex")).otherwise(F.expr("low rlike regex"))
    found = F.struct((F.col("form") == "host").cast("int").alias("host_form"), F.length("name").alias("length"), "name", "verdict")
    judged = (
        probes.join(F.broadcast(index), "token", "left")
        .groupBy("row")
        .agg(*(F.first(c).alias(c) for c in ("id", "host", "path")), F.max(F.when(fits, found)).alias("best"))
    )
    return judged.select(
        F.col("id").alias(id_col), "host", "path",
        F.when(F.col("best.host_form") == 1, F.col("best.name")).alias("rule"),
        F.coalesce("best.verdict", F.lit(default)).alias("verdict"),
    )
