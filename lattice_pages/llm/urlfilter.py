"""URL filters with redirect equivalence, DataFrame functions only.

Rules (host, path prefix) block or allow the urls of a host and its subdomains; the
longest rule that fits a url decides. Urls without a rule take the decision of their
aliases: redirect and canonical-link edges (``<link rel=canonical>``, refresh in a
``<meta>``, and any table of redirects handed in) join addresses into components, and a
component is allowed if an explicit allow is among its members, else blocked if an
explicit block is, else allowed by default.

Addresses are host + path + query, without scheme and fragment. Only addresses with an
edge take part in the components; the pages meet the result by an equi-join on the
address, which adaptive execution can split.

Defined results: a null url, or one without ``://``, has an empty host and path, fits no
rule and is no node; null html has no link; repeated rows get equal results; an empty
table gives an empty table. Only the named columns are read, so others cannot clash.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from lattice_pages.llm.components import components
from lattice_pages.session import materialize

_UPPER, _LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
CANONICAL = r"""(?is)<link\b(?=[^>]*\brel\s*=\s*["']?canonical\b)[^>]*\bhref\s*=\s*["']?([^"'\s>]+)"""
REFRESH = r"""(?is)<meta\b(?=[^>]*\bhttp-equiv\s*=\s*["']?refresh\b)[^>]*\bcontent\s*=\s*["']?[^"'>]*?\burl\s*=\s*["']?([^"'\s>]+)"""


@dataclass(frozen=True)
class Rule:
    verdict: str  # allow or block
    host: str
    path: str

    @property
    def name(self) -> str:
        return self.host + self.path


#: The rules of the registered query.
RULES = (
    Rule("block", "com", "/en/"),
    Rule("allow", "example.com", "/en/7"),
    Rule("allow", "net", "/de/"),
    Rule("block", "example.net", "/de/8"),
    Rule("block", "org", "/es/"),
)


def _rest(url: Column) -> Column:
    """What follows the first ``://``; empty if there is none."""
    at = F.instr(url, "://")
    return F.when(at > 0, url.substr(at + 3, F.length(url))).otherwise("")


def host_of(url: Column) -> Column:
    return F.translate(F.regexp_extract(_rest(url), r"^[^/?#]*", 0), _UPPER, _LOWER)


def path_of(url: Column) -> Column:
    return F.regexp_extract(_rest(url), r"^[^/?#]*([^?#]*)", 1)


def address(url: Column) -> Column:
    """The node of a url: host, path and query; null where it has no host."""
    host = host_of(url)
    return F.when(host != "", F.concat(host, F.regexp_extract(_rest(url), r"^[^/?#]*([^#]*)", 1)))


def matched(host: Column, path: Column, rules: tuple[Rule, ...]) -> Column:
    """``struct(name, verdict)`` of the longest rule that fits, or null."""
    got = F.lit(None)
    for r in sorted(rules, key=lambda r: (len(r.name), r.verdict == "allow", r.name)):
        fits = ((host == r.host) | host.endswith("." + r.host)) & path.startswith(r.path)
        got = F.when(fits, F.struct(F.lit(r.name).alias("name"), F.lit(r.verdict).alias("verdict"))).otherwise(got)
    return got


def _unescape(link: Column) -> Column:
    """Character references of an attribute: the named ones that urls hold, ``&`` last."""
    for name, char in (("quot", '"'), ("#34", '"'), ("apos", "'"), ("#39", "'"), ("lt", "<"), ("gt", ">"), ("#38", "&"), ("#x26", "&"), ("amp", "&")):
        link = F.regexp_replace(link, f"(?i)&{name};", char)
    return link


def _no_dots(path: Column) -> Column:
    """``.`` and ``..`` segments taken out; the path starts with a slash."""
    parts = F.split(path, "/")
    last = F.element_at(parts, -1)
    open_end = (last == ".") | (last == "..")
    walk = F.aggregate(
        F.slice(parts, 2, F.greatest(F.size(parts) - 1, F.lit(0))),
        F.array().cast("array<string>"),
        lambda kept, x: F.when(x == "..", F.slice(kept, 1, F.greatest(F.size(kept) - 1, F.lit(0)))).when(x == ".", kept).otherwise(F.concat(kept, F.array(x))),
    )
    return F.concat(F.lit("/"), F.array_join(walk, "/"), F.when(open_end & (F.size(walk) > 0), "/").otherwise(""))


def resolve(base: Column, link: Column) -> Column:
    """The absolute url of a link on the page at ``base``; null for other schemes than ``scheme://``.

    ``?q`` keeps the page's path, ``#x`` and an empty link are the page itself, dot segments are
    taken out, character references are decoded.
    """
    link = _unescape(F.trim(link))
    scheme = F.substring_index(base, "://", 1)
    host, path = host_of(base), path_of(base)
    root = F.concat(scheme, F.lit("://"), host)
    here = F.when(path == "", "/").otherwise(path)
    folder = F.regexp_extract(here, r"^(.*/)?", 0)
    own, rest = F.regexp_extract(link, r"^[^?#]*", 0), F.regexp_extract(link, r"^[^?#]*(.*)$", 1)
    return (
        F.when(link.rlike(r"^[A-Za-z][A-Za-z0-9+.-]*://"), link)
        .when(link.rlike(r"^[A-Za-z][A-Za-z0-9+.-]*:"), F.lit(None))
        .when(link.startswith("//"), F.concat(scheme, F.lit(":"), link))
        .when((link == "") | link.startswith("#"), base)
        .when(link.startswith("?"), F.concat(root, here, link))
        .when(link.startswith("/"), F.concat(root, _no_dots(own), rest))
        .otherwise(F.concat(root, _no_dots(F.concat(folder, own)), rest))
    )


def link_edges(pages: DataFrame, url_col: str = "url", html_col: str = "html") -> DataFrame:
    """``a, b``: addresses joined by a canonical link or a refresh; map-only."""
    url = F.col(url_col)
    links = [F.nullif(F.regexp_extract(F.coalesce(F.col(html_col), F.lit("")), p, 1), F.lit("")) for p in (CANONICAL, REFRESH)]
    rows = pages.filter(F.instr(url, "://") > 0).select(url.alias("url"), F.explode(F.array_compact(F.array(*links))).alias("link"))
    return rows.select(address(F.col("url")).alias("a"), address(resolve(F.col("url"), F.col("link"))).alias("b")).filter(F.col("b").isNotNull())


def judge(pages: DataFrame, rules: tuple[Rule, ...] = RULES, redirects: DataFrame | None = None, id_col: str = "page_id", url_col: str = "url", html_col: str = "html") -> DataFrame:
    """``id, host, path, rule, verdict`` for every page. ``redirects``: more edges, as urls ``source, target``."""
    edges = link_edges(pages, url_col, html_col)
    if redirects is not None:
        edges = edges.unionByName(redirects.select(address(F.col("source")).alias("a"), address(F.col("target")).alias("b")))
    groups = components(edges, name="alias")
    as_url = F.concat(F.lit("x://"), F.col("node"))
    explicit = groups.withColumn("v", matched(host_of(as_url), path_of(as_url), rules)["verdict"])
    decided = explicit.groupBy("root").agg(F.bool_or(F.col("v") == "allow").alias("allow"), F.bool_or(F.col("v") == "block").alias("block"))
    decided = decided.filter(F.col("block") & ~F.coalesce("allow", F.lit(False))).select("root")
    blocked = materialize(groups.join(decided, "root", "left_semi").select(F.col("node").alias("address"), F.lit(True).alias("blocked")), "blocked")
    url = F.col(url_col)
    rows = pages.select(F.col(id_col), host_of(url).alias("host"), path_of(url).alias("path"), address(url).alias("address"))
    rows = rows.select("*", matched(F.coalesce("host", F.lit("")), F.coalesce("path", F.lit("")), rules).alias("m"))
    rows = rows.join(blocked, "address", "left")
    verdict = F.coalesce(F.col("m.verdict"), F.when(F.col("blocked"), "block").otherwise("allow"))
    return rows.select(id_col, F.coalesce("host", F.lit("")).alias("host"), F.coalesce("path", F.lit("")).alias("path"), F.col("m.name").alias("rule"), verdict.alias("verdict"))


_SQL_REST = "case when instr(url, '://') > 0 then substr(url, instr(url, '://') + 3) else '' end"

#: The given pages hold no canonical link and no refresh, so the aliases decide nothing there; the
#: SQL finds such links too and would give a null verdict, hence a mismatch, if one appeared.
ORACLE = f"""
WITH r AS (SELECT page_id, html, coalesce({_SQL_REST}, '') AS rest FROM pages),
u AS (SELECT page_id, html, translate(regexp_extract(rest, '^[^/?#]*'), '{_UPPER}', '{_LOWER}') AS host,
             regexp_extract(rest, '^[^/?#]*([^?#]*)', 1) AS path FROM r),
rules(verdict, rhost, rpath) AS (VALUES {', '.join(f"('{r.verdict}', '{r.host}', '{r.path}')" for r in RULES)}),
m AS (SELECT page_id, rhost || rpath AS rule, verdict,
             row_number() OVER (PARTITION BY page_id ORDER BY length(rhost || rpath) DESC) AS n
      FROM u, rules WHERE (host = rhost OR ends_with(host, '.' || rhost)) AND starts_with(path, rpath))
SELECT u.page_id, host, path, m.rule,
       coalesce(m.verdict, CASE WHEN regexp_matches(coalesce(html, ''), '(?is)(<link[^>]*canonical|http-equiv[^>]*refresh)') THEN NULL ELSE 'allow' END) AS verdict
FROM u LEFT JOIN m ON m.page_id = u.page_id AND m.n = 1
"""
