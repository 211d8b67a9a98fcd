"""URL filter: rules indexed by their rarest literal token.

A rule is (verdict, host, path). It fits its host and all subdomains of it when the URL's path starts
with the rule's path. The longest fitting rule decides; where none fits, the default verdict holds.

Every rule is filed under one literal token that any fitting URL must hold: a label of its host or a
complete segment of its path, whichever is rarest over the corpus. The tokens of a URL fetch candidate rules,
and only those run their regular expression. DataFrame functions only.

Defined cases: a null URL or one without ``://`` has an empty host and path, fits no rule and gets the default
verdict. Repeated rows stay repeated. An empty table gives an empty result. Further columns of the input pass
through unless they bear a name of the result, in which case the result's column takes their place.
"""

from __future__ import annotations

import re
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import lower_ascii, table

DEFAULT_VERDICT = "allow"
#: Up to so many rules the index is a literal of the plan; beyond, a joined table.
LITERAL_RULES = 512


@dataclass(frozen=True)
class UrlRule:
    verdict: str
    host: str
    path: str

    @property
    def name(self) -> str:
        return f"{self.host}{self.path}"

    def tokens(self) -> list[str]:
        """Tokens that every fitting URL holds. The last path segment counts only if a slash ends it."""
        labels = [f"h:{x}" for x in self.host.split(".") if x]
        return labels + [f"p:{x}" for x in self.path.split("/")[:-1] if x]

    def regex(self) -> str:
        """Over host and path written together, as ``host`` never holds a slash."""
        quote = lambda s: re.sub(r"([^A-Za-z0-9/_ -])", r"\\\1", s)
        return f"(?s)^(?:[^/?#]*\\.)?{quote(self.host)}{quote(self.path)}.*" if self.path else f"(?s)^(?:[^/?#]*\\.)?{quote(self.host)}(?:/.*)?$"


#: Rules of the registered query. Fixed values.
RULES = (
    UrlRule("block", "com", "/en/"),
    UrlRule("allow", "example.com", "/en/7"),
    UrlRule("block", "example.net", "/de/8"),
    UrlRule("allow", "net", "/de/"),
    UrlRule("block", "org", "/es/"),
)


def host_and_path(url: Column) -> tuple[Column, Column]:
    parts = r"(?s)^.*?://([^/?#]*)([^?#]*)"
    empty = F.lit("")
    return (
        lower_ascii(F.coalesce(F.regexp_extract(url, parts, 1), empty)),
        F.coalesce(F.regexp_extract(url, parts, 2), empty),
    )


def url_tokens(host: Column, path: Column) -> Column:
    tag = lambda col, sep, mark: F.transform(F.split(col, sep, -1), lambda x: F.concat(F.lit(mark), x))
    return F.array_distinct(F.concat(tag(host, r"\.", "h:"), tag(path, "/", "p:")))


def rule_index(pages: DataFrame, rules: tuple[UrlRule, ...], tokens: Column) -> dict[str, list[UrlRule]]:
    """Each rule under its rarest token. Counts cover all rows; only counts of the rules' own tokens reach the driver."""
    wanted = sorted({t for r in rules for t in r.tokens()})
    spark = pages.sparkSession
    vocabulary = F.broadcast(spark.createDataFrame([(t,) for t in wanted], "token string"))
    counts = pages.select(F.explode(tokens).alias("token")).join(vocabulary, "token").groupBy("token").count()
    seen = {r["token"]: r["count"] for r in counts.collect()}
    index: dict[str, list[UrlRule]] = {}
    for rule in rules:
        if not rule.tokens():
            raise ValueError(f"{rule} has no token to be filed under")
        index.setdefault(min(rule.tokens(), key=lambda t: (seen.get(t, 0), t)), []).append(rule)
    return index


def _best(candidates: Column, address: Column) -> Column:
    """The longest candidate whose regular expression fits."""
    fitting = F.filter(candidates, lambda c: F.call_function("rlike", address, c["regex"]))
    return F.array_max(F.transform(fitting, lambda c: F.struct(F.length(c["rule"]).alias("size"), c["rule"].alias("rule"), c["verdict"].alias("verdict"))))


def judge_urls(pages: DataFrame, rules: tuple[UrlRule, ...] = RULES, url: str = "url", default: str = DEFAULT_VERDICT) -> DataFrame:
    """``pages`` with host, path, rule and verdict."""
    made = ("host", "path", "rule", "verdict")
    base = pages.drop(*(c for c in pages.columns if c.lower() in made and c != url))
    host, path = host_and_path(F.col(url))
    base = base.withColumns({"host": host, "path": path}) if url not in made else base
    tokens = url_tokens(F.col("host"), F.col("path"))
    index = rule_index(base, rules, tokens)
    address = F.concat("host", "path")
    spark = pages.sparkSession
    entry = lambda r: F.struct(F.lit(r.regex()).alias("regex"), F.lit(r.name).alias("rule"), F.lit(r.verdict).alias("verdict"))
    if len(rules) <= LITERAL_RULES:
        book = F.create_map(*(x for t, rs in index.items() for x in (F.lit(t), F.array(*(entry(r) for r in rs)))))
        candidates = F.flatten(F.filter(F.transform(tokens, lambda t: F.element_at(book, t)), lambda x: x.isNotNull()))
        judged = base.withColumn("_best", _best(candidates, address))
    else:
        # by distinct address, so that a hot host costs nothing; the index goes to the side Catalyst sizes
        rows = [(t, r.regex(), r.name, r.verdict) for t, rs in index.items() for r in rs]
        book = spark.createDataFrame(rows, "token string, regex string, rule string, verdict string")
        seen = base.select("host", "path").distinct().withColumn("token", F.explode(tokens)).join(book, "token")
        fits = seen.where(F.call_function("rlike", address, F.col("regex")))
        best = fits.groupBy("host", "path").agg(F.max(F.struct(F.length("rule").alias("size"), "rule", "verdict")).alias("_best"))
        judged = base.join(best, ["host", "path"], "left")
    return judged.withColumns({"rule": F.col("_best.rule"), "verdict": F.coalesce("_best.verdict", F.lit(default))}).drop("_best")


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    pages = table(spark, sf_dir, "pages").select("page_id", "url")
    return judge_urls(pages).select("page_id", "host", "path", "rule", "verdict")


def oracle() -> str:
    fits = lambda r: f"((host = '{r.host}' or ends_with(host, '.{r.host}')) and starts_with(path, '{r.path}'))"
    ordered = sorted(RULES, key=lambda r: -len(r.name))
    pick = lambda field: "case " + " ".join(f"when {fits(r)} then '{getattr(r, field)}'" for r in ordered)
    return f"""
with cut as (
  select page_id, case when strpos(url, '://') > 0 then substr(url, strpos(url, '://') + 3) else '' end as rest from pages),
ends as (
  select page_id, rest, length(regexp_replace(rest, '[/?#](.|\\n)*$', '')) as h from cut),
parts as (
  select page_id, translate(substr(rest, 1, h), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') as host,
         regexp_replace(substr(rest, h + 1), '[?#](.|\\n)*$', '') as path from ends)
select page_id, host, path, {pick('name')} else null end as rule, {pick('verdict')} else '{DEFAULT_VERDICT}' end as verdict from parts"""
