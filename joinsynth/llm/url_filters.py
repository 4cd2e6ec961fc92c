"""URL filters with redirect equivalence.

Rules are (host, path) pairs; a rule fits its host and every subdomain where the path starts
with the rule's path, and the longest fitting rule decides.  Redirects (``meta refresh`` or
rows of a redirect table) and canonical links are edges between urls; distributed connected
components over them make aliases.  Targets are resolved against their page's url, character
references decoded; scheme and host of all ends are compared without case.  A page without a rule of its own is blocked if any url of
its component is blocked by a rule; an explicit allow rule on the page itself takes precedence
over what its aliases say (``allow_wins='group'``: an allow rule on any alias does).

Defined results: a null url, or one without ``://``, has empty host and path and no rule;
null html has no links; repeated pages are each judged; an empty table gives an empty result.
"""

from __future__ import annotations

import json
from collections.abc import Sequence
from html.entities import html5
from typing import NamedTuple

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import ascii_lower, cut
from .components import components


class Rule(NamedTuple):
    verdict: str
    host: str
    path: str


#: Rules up to this number are one expression; longer lists are joined by host suffix.
INLINE_RULES = 64
#: Most bytes of aliases that are broadcast to the pages; more are joined by a shuffle.
BROADCAST_BYTES = 16 << 20

# Fixed patterns of the two kinds of link in a page's head.
_CANONICAL = (r"""(?is)<link\b[^>]*\brel\s*=\s*["']?canonical\b[^>]*>""", r"""(?is)\bhref\s*=\s*["']?([^"'\s>]+)""")
_REFRESH = (r"""(?is)<meta\b[^>]*\bhttp-equiv\s*=\s*["']?refresh\b[^>]*>""", r"""(?is)\burl\s*=\s*["']?((?:&#?\w+;|[^"'\s>;])+)""")
# Scheme, user, host and port, path, query.
_URL = r"^([A-Za-z][A-Za-z0-9+.-]*)://([^/?#@]*@)?([^/?#]*)([^?#]*)(\?[^#]*)?"
_TOKEN = r"&#[0-9]{1,7};?|&#[xX][0-9a-fA-F]{1,6};?|&[A-Za-z][A-Za-z0-9]*(?:;|(?![A-Za-z0-9=;]))|[^&]+|&"


def split_url(url: Column) -> tuple[Column, Column]:
    """(host, path): both empty where the url is null or has no ``://``."""
    at = F.instr(url, "://")
    rest = F.when(at > 0, url.substr(at + 3, F.length(url))).otherwise("")
    host = ascii_lower(F.regexp_extract(rest, r"^([^/?#]*)", 1))
    path = F.regexp_extract(rest, r"^[^/?#]*([^?#]*)", 1)
    return F.coalesce(host, F.lit("")), F.coalesce(path, F.lit(""))


def _ordered(rules: Sequence[Rule]) -> list[Rule]:
    return sorted(rules, key=lambda r: (-len(r.host + r.path), -len(r.host), r.verdict != "allow", r))


def with_rule(frame: DataFrame, rules: Sequence[Rule]) -> DataFrame:
    """Adds ``rule`` and ``rule_verdict`` (null where no rule fits) by ``host`` and ``path``."""
    ranked = _ordered(rules)
    if len(ranked) <= INLINE_RULES:
        rule, verdict = F.lit(None).cast("string"), F.lit(None).cast("string")
        for r in reversed(ranked):
            fits = ((F.col("host") == r.host) | F.col("host").endswith("." + r.host)) & F.col("path").startswith(r.path)
            rule, verdict = F.when(fits, r.host + r.path).otherwise(rule), F.when(fits, r.verdict).otherwise(verdict)
        return frame.withColumns({"rule": rule, "rule_verdict": verdict})
    spark = frame.sparkSession
    listed = spark.createDataFrame([(-i, r.host, r.path, r.host + r.path, r.verdict) for i, r in enumerate(ranked)], "pref int, r_host string, r_path string, rule string, rule_verdict string")
    pairs = frame.select("host", "path").distinct()
    labels = F.split("host", r"\.")
    suffix = F.transform(F.sequence(F.lit(1), F.size(labels)), lambda i: F.array_join(F.slice(labels, i, F.size(labels)), "."))
    best = (
        pairs.withColumn("r_host", F.explode(suffix)).join(listed, "r_host").filter("startswith(path, r_path)")
        .groupBy("host", "path").agg(F.max(F.struct("pref", "rule", "rule_verdict")).alias("best"))
        .select("host", "path", "best.rule", "best.rule_verdict")
    )
    return frame.join(best, ["host", "path"], "left")


def unescaped(text: Column) -> Column:
    """``text`` of an attribute with its character references decoded, each once."""
    names = F.from_json(F.lit(json.dumps(html5)), "map<string,string>")

    def one(t: Column) -> Column:
        digits = F.regexp_extract(t, "^&#([0-9]+)", 1)
        code = F.when(digits != "", digits.cast("int")).otherwise(F.conv(F.regexp_extract(t, "^&#[xX]([0-9a-fA-F]+)", 1), 16, 10).cast("int"))
        real = code.between(1, 0xD7FF) | code.between(0xE000, 0x10FFFF)
        char = F.when(real, F.decode(F.unhex(F.lpad(F.hex(code.cast("bigint")), 8, "0")), "UTF-32"))
        return F.when(t.rlike("^&#[0-9xX]"), F.coalesce(char, t)).when(t.startswith("&"), F.coalesce(F.try_element_at(names, t.substr(F.lit(2), F.length(t))), t)).otherwise(t)

    return F.when(text.contains("&"), F.array_join(F.transform(F.regexp_extract_all(text, F.lit(_TOKEN), F.lit(0)), one), "")).otherwise(text)


def _without_dots(path: Column) -> Column:
    """Segments ``.`` and ``..`` carried out."""
    parts = F.split(path, "/", -1)
    step = lambda done, x: F.when(x == ".", done).when(x == "..", F.slice(done, F.lit(1), F.greatest(F.size(done) - 1, F.lit(1)))).otherwise(F.concat(done, F.array(x)))
    done = F.aggregate(parts, F.array().cast("array<string>"), step)
    ended = F.when(path.rlike(r"/\.\.?$"), F.concat(done, F.array(F.lit("")))).otherwise(done)
    return F.when(path.rlike(r"/\.\.?(/|$)"), F.array_join(ended, "/")).otherwise(path)


def alias_url(url: Column) -> Column:
    """The url as a vertex: no fragment, scheme and host in lower case, no dot segments."""
    part = lambda k: F.regexp_extract(url, _URL, k)
    whole = F.concat(ascii_lower(part(1)), F.lit("://"), part(2), ascii_lower(part(3)), _without_dots(part(4)), part(5))
    return F.when(url.rlike(_URL), whole).otherwise(F.regexp_replace(url, r"#.*$", ""))


def resolved(base: Column, target: Column) -> Column:
    """``target`` as an absolute url seen from ``base``; null for other schemes, and for relative ones if ``base`` is not absolute."""
    part = lambda k: F.regexp_extract(base, _URL, k)
    origin = F.when(base.rlike(_URL), F.concat(part(1), F.lit("://"), part(2), part(3)))
    folder = F.when(part(4) == "", "/").otherwise(F.regexp_replace(part(4), "[^/]*$", ""))
    return (
        F.when(target.rlike("^[A-Za-z][A-Za-z0-9+.-]*://"), target).when(target.rlike("^[A-Za-z][A-Za-z0-9+.-]*:"), F.lit(None).cast("string"))
        .when(target.startswith("//"), F.when(origin.isNotNull(), F.concat(part(1), F.lit(":"), target)))
        .when(target.startswith("/"), F.concat(origin, target))
        .when(target.startswith("?"), F.concat(origin, part(4), target))
        .when(target.startswith("#"), base)
        .otherwise(F.concat(origin, folder, target))
    )


def page_links(pages: DataFrame, url_col: str = "url", html_col: str = "html") -> DataFrame:
    """(a, b) url pairs from all canonical links and meta refreshes, as :func:`alias_url` writes them."""
    targets = lambda tag, target: F.transform(F.regexp_extract_all(html_col, F.lit(tag), F.lit(0)), lambda t: F.regexp_extract(t, target, 1))
    every = [targets(*kind) for kind in (_CANONICAL, _REFRESH)]
    links = pages.filter(F.col(url_col).isNotNull() & F.col(html_col).isNotNull()).select(F.col(url_col).alias("a"), F.explode(F.concat(*every)).alias("b")).filter("b != ''")
    return _as_aliases(links.withColumn("b", unescaped(F.col("b"))))


def _as_aliases(links: DataFrame, whole: bool = False) -> DataFrame:
    """(a, b) with ``b`` resolved against ``a``, both as vertices; ``whole``: what can't be resolved stays as it is."""
    # step by step behind fences: each function names its argument many times
    full = resolved(F.col("a"), F.col("b"))
    for c, to in (("b", F.coalesce(full, "b") if whole else full), ("b", alias_url(F.col("b"))), ("a", alias_url(F.col("a")))):
        links = links.select("a", "b", F.explode(F.array(F.struct("a", "b"))).alias("at")).select("at.a", "at.b").withColumn(c, to)
    return links.filter("b is not null")


def judge_urls(pages: DataFrame, rules: Sequence[Rule], redirects: DataFrame | None = None, default: str = "allow", allow_wins: str = "page", id_col: str = "page_id", url_col: str = "url", html_col: str = "html") -> DataFrame:
    """One row per page: ``page_id, host, path, rule, verdict, component`` (component: least alias url, null if none)."""
    host, path = split_url(F.col("url"))
    base = pages.select(F.col(id_col).alias("page_id"), F.col(url_col).alias("url"))
    judged = with_rule(base.withColumns({"host": host, "path": path}), rules).withColumn("alias", alias_url(F.col("url")))
    links = page_links(pages, url_col, html_col)
    if redirects is not None:
        links = links.unionByName(_as_aliases(redirects.select("a", "b"), whole=True))
    tree = components(links)
    # every vertex of a component with its least url, the least itself included
    group = tree.select(F.col("v").alias("alias"), "component").unionByName(tree.select(F.col("component").alias("alias"), "component").distinct())
    g_host, g_path = split_url(F.col("alias"))
    votes = (
        with_rule(group.withColumns({"host": g_host, "path": g_path}), rules)
        .groupBy("component").agg(F.max(F.expr("rule_verdict = 'block'")).alias("blocked"), F.max(F.expr("rule_verdict = 'allow'")).alias("allowed"))
    )
    spared = F.coalesce(F.col("allowed"), F.lit(False)) if allow_wins == "group" else F.lit(False)
    passed = F.when(F.coalesce(F.col("blocked"), F.lit(False)) & ~spared, "block").otherwise(default)
    # one row an alias; pages without an alias meet no key at all
    known = cut(group.join(votes, "component"))
    size = known.agg(F.coalesce(F.sum(F.octet_length("alias") + F.octet_length("component") + 32), F.lit(0))).first()[0]
    known = F.broadcast(known) if size <= BROADCAST_BYTES else known
    found = judged.filter("alias is not null").join(known, "alias", "left")
    none = judged.filter("alias is null").withColumns({"component": F.lit(None).cast("string"), "blocked": F.lit(None).cast("boolean"), "allowed": F.lit(None).cast("boolean")})
    return found.unionByName(none).select("page_id", "host", "path", "rule", F.coalesce("rule_verdict", passed).alias("verdict"), "component")
