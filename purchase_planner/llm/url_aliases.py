"""URL filter whose decisions follow redirects and canonical links.

Rules (host, path, verdict) apply to a host and its subdomains where the url's path starts with the rule's; the longest
rule wins, on equal length an allow. Pages that no rule fits take the verdict of their aliases: addresses are the nodes,
redirect (meta refresh), canonical-link and address-form edges join them, and the connected components are computed
distributedly. In a component an explicit allow takes precedence over any block; without either the default holds.

Address-form edges tie each url to the form that servers redirect to: no scheme, no www. or m. label, no query or
fragment, no .html, no trailing slash.

Links are read from canonical link and refresh elements, decoded and resolved against the page's base; a chain or a hub of
any size is one component.

Defined cases: a null url, or one without ://, has empty host and path, fits no rule and has no aliases, so it gets the
default verdict; an empty host fits no rule; rows keep their multiplicity; equal urls are one node; a null html has no
links; links to other schemes (mailto:) or to the page itself are none; an empty table, or an empty table of redirects,
gives an empty result or no further links; other columns are not read, so they may have any names.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ._shared import settle
from .components import components


@dataclass(frozen=True)
class Rule:
    host: str
    path: str  # begins with /
    verdict: str  # allow or block

    @property
    def name(self) -> str:
        return self.host + self.path


#: The rules of the contract of op2.
RULES = (
    Rule("com", "/", "allow"),
    Rule("example.com", "/en/", "block"),
    Rule("www.example.com", "/en/", "allow"),
    Rule("net", "/es/", "block"),
    Rule("net", "/fr/", "block"),
)
_UPPER, _LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"


def lower_ascii(c: Column) -> Column:
    return F.translate(c, _UPPER, _LOWER)


def host_of(url: Column) -> Column:
    return F.when(F.instr(url, "://") > 0, lower_ascii(F.regexp_extract(url, r"(?s)^.*?://([^/?#]*)", 1))).otherwise(F.lit(""))


def path_of(url: Column) -> Column:
    return F.when(F.instr(url, "://") > 0, F.regexp_extract(url, r"(?s)^.*?://[^/?#]*([^?#]*)", 1)).otherwise(F.lit(""))


def matching_rule(host: Column, path: Column, rules: tuple[Rule, ...]) -> Column:
    """The name of the longest fitting rule, else null; a rule list is a short constant, so this is one expression."""
    out = F.lit(None).cast("string")
    for r in sorted(rules, key=lambda r: (len(r.name), r.verdict == "allow")):
        fits = (host.eqNullSafe(F.lit(r.host)) | F.endswith(host, F.lit("." + r.host))) & F.startswith(path, F.lit(r.path))
        out = F.when(fits, F.lit(r.name)).otherwise(out)
    return out


def plain_form(url: Column) -> Column:
    """The address that the variants of one page share; null without ://."""
    host = F.regexp_replace(host_of(url), r"^(www|m)\.", "")
    path = F.regexp_replace(F.regexp_replace(path_of(url), r"/+$", ""), r"\.html$", "")
    return F.when(F.instr(url, "://") > 0, F.concat(host, F.lit("/"), F.regexp_replace(path, "^/", "")))


def decoded(ref: Column) -> Column:
    """A link's text without the character references that stand in links, and without the blanks that browsers drop."""
    out = F.regexp_replace(F.regexp_replace(ref, r"[\t\n\r]", ""), r"^[\x00-\x20]+|[\x00-\x20]+$", "")
    for pattern, by in ((r"(?i)&(?:quot|#34|#x22);", '"'), (r"(?i)&(?:apos|#39|#x27);", "'"), (r"(?i)&(?:sol|#47|#x2f);", "/"), (r"(?i)&(?:colon|#58|#x3a);", ":"), (r"(?i)&(?:amp|#38|#x26);", "&")):
        out = F.regexp_replace(out, pattern, by)
    return out


def _without_dots(path: Column) -> Column:
    """A path with its . and .. segments resolved."""
    parts = F.split(path, "/", -1)
    step = lambda out, x: F.when(x == "..", F.slice(out, F.lit(1), F.greatest(F.size(out) - 1, F.lit(1)))).when(x == ".", out).otherwise(F.concat(out, F.array(x)))
    kept = F.aggregate(F.slice(parts, F.lit(2), F.size(parts)), F.array(F.lit("")), step)
    return F.concat(F.array_join(kept, "/"), F.when(path.rlike(r"/\.\.?$"), F.lit("/")).otherwise(F.lit("")))


def resolved(base: Column, ref: Column) -> Column:
    """A link's target as an absolute url, from the address that it stands in; null where it leads nowhere else."""
    scheme, origin = F.regexp_extract(base, r"(?s)^(.*?:)//", 1), F.regexp_extract(base, r"(?s)^(.*?://[^/?#]*)", 1)
    path = F.when(path_of(base) == "", F.lit("/")).otherwise(path_of(base))
    plain, rest = F.regexp_extract(ref, r"(?s)^([^?#]*)", 1), F.regexp_extract(ref, r"(?s)^[^?#]*(.*)$", 1)
    folder = F.regexp_extract(path, r"(?s)^(.*/)", 1)
    return (
        F.when((ref == "") | F.startswith(ref, F.lit("#")), F.lit(None).cast("string"))
        .when(ref.rlike(r"(?s)^[A-Za-z][A-Za-z0-9+.-]*://"), ref)
        .when(ref.rlike(r"(?s)^[A-Za-z][A-Za-z0-9+.-]*:"), F.lit(None).cast("string"))
        .when(~(F.instr(base, "://") > 0), F.lit(None).cast("string"))
        .when(F.startswith(ref, F.lit("//")), F.concat(scheme, ref))
        .when(F.startswith(ref, F.lit("/")), F.concat(origin, _without_dots(plain), rest))
        .when(F.startswith(ref, F.lit("?")), F.concat(origin, path, ref))
        .otherwise(F.concat(origin, _without_dots(F.concat(folder, plain)), rest))
    )


_HREF = r"(?is)\bhref\s*=\s*(?:\"([^\"]*)\"|'([^']*)'|([^\s\"'>]+))"


def _href(tag: Column) -> Column:
    return decoded(F.concat(*[F.regexp_extract(tag, _HREF, k) for k in (1, 2, 3)]))


def link_edges(pages: DataFrame, url_col: str = "url", html_col: str = "html") -> DataFrame:
    """(src, dst) addresses: canonical links and meta refreshes found in the html.

    Targets are decoded and resolved against the page's base element or its url.
    """
    html, url = F.col(html_col), F.col(url_col)
    tags = F.regexp_extract_all(html, F.lit(r"(?is)(<link\b[^>]*\brel\s*=\s*[\"']?canonical\b[^>]*>|<meta\b[^>]*\bhttp-equiv\s*=\s*[\"']?refresh\b[^>]*>)"), F.lit(1))
    based = _href(F.regexp_extract(html, r"(?is)(<base\b[^>]*>)", 1))
    found = pages.where(html.rlike("(?i)canonical|refresh") & url.isNotNull()).select(url.alias("src"), F.coalesce(resolved(url, based), url).alias("base"), F.explode(tags).alias("tag"))
    refresh = decoded(F.regexp_extract("tag", r"(?is)\burl\s*=\s*[\"']?([^\"'\s>]+)", 1))
    ref = F.when(F.col("tag").rlike("(?i)^<link"), _href(F.col("tag"))).otherwise(refresh)
    return found.select("src", resolved(F.col("base"), ref).alias("dst")).where("dst is not null")


def judge(pages: DataFrame, rules: tuple[Rule, ...] = RULES, redirects: DataFrame | None = None, default: str = "allow", id_col: str = "page_id", url_col: str = "url", html_col: str | None = "html") -> DataFrame:
    """id, host, path, rule, verdict and alias_verdict of every page. redirects: further (src, dst) urls."""
    by_name = {r.name: r.verdict for r in rules}
    named = F.create_map(*[F.lit(x) for pair in by_name.items() for x in pair]) if by_name else F.lit(None).cast("map<string,string>")
    url = F.col("url")
    base = pages.select(F.col(id_col).alias("__id"), F.col(url_col).cast("string").alias("url"))
    base = base.withColumn("host", host_of(url)).withColumn("path", path_of(url)).withColumn("rule", matching_rule(F.col("host"), F.col("path"), rules))
    base = base.withColumn("form", plain_form(url)).withColumn("own", named[F.col("rule")])
    # forms are the nodes: the edge between a url and its form is contracted, which leaves the links between forms
    links = link_edges(pages, url_col, html_col) if html_col else None
    if redirects is not None:
        more = redirects.select("src", "dst")
        links = more if links is None else links.unionByName(more)
    key = F.col("form")
    if links is not None:
        links = settle(links)  # the html is read once
        edges = links.select(plain_form(F.col("src")).alias("src"), plain_form(F.col("dst")).alias("dst")).where("src is not null and dst is not null and src <> dst").distinct()
        # nodes go by 64-bit hashes of their forms; a component is only a key
        hashed = components(edges.select(F.xxhash64("src").alias("src"), F.xxhash64("dst").alias("dst")))
        forms = edges.select(F.col("src").alias("form")).unionByName(edges.select(F.col("dst").alias("form"))).distinct()
        joined = settle(forms.join(hashed, F.xxhash64("form") == F.col("node")).select("form", F.concat(F.lit("#"), F.col("component").cast("string")).alias("component")))
        base = base.join(joined, "form", "left")
        key = F.coalesce("component", "form")
        # what links name counts too, even where no page of that address is among the rows
        ends = links.select(F.col("src").alias("url")).unionByName(links.select(F.col("dst").alias("url"))).distinct()
        ends = ends.withColumn("own", named[matching_rule(host_of(url), path_of(url), rules)]).where("own is not null").withColumn("form", plain_form(url))
        ends = ends.join(joined, "form").select(F.col("component").alias("key"), "own")
    base = base.withColumn("key", key)
    said = base.where("own is not null and key is not null").select("key", "own")
    if links is not None:
        said = said.unionByName(ends)
    # pages of a component agree by a combinable aggregate; allow sorts before block, so the least is the precedence
    verdicts = said.groupBy("key").agg(F.min("own").alias("alias_verdict"))
    out = base.join(verdicts, "key", "left")
    return out.select(F.col("__id").alias(id_col), "host", "path", "rule", F.coalesce("own", "alias_verdict", F.lit(default)).alias("verdict"), F.col("key").alias("alias_group"), "alias_verdict")
