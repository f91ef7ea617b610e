"""URL filters: host and path rules, then redirect equivalence, in DataFrame functions only.

A url's own rule decides it.  Urls without a rule take the decision of their aliases: urls with the same normal form
(scheme, query, fragment, a leading www. or m., a trailing slash and .html dropped) and urls tied to them by canonical
links or redirects found in the pages (all of a page, relative ones resolved against its url), through connected components.  If any alias is allowed by a rule the class is
allowed, else if any is blocked it is blocked, else it is allowed.

Defined results: a null url or one without :// has empty host and path, no alias, and verdict allow unless a rule
fits the empty host (none can); null html has no links; repeated rows get equal results; an empty table gives none.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from momenttree.llm.components import components
from momenttree.llm.runtime import cut

#: Host, path, verdict.
RULES = [("org", "/", "allow"), ("example.org", "/es/", "block"), ("example.org", "/en/1", "block"), ("com", "/fr/", "allow"), ("com", "/de/", "block")]
#: Rules are part of the plan, so their number is bounded.
RULES_MOST = 2_000
UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"


def _after_scheme(url: Column) -> Column:
    """What follows the first ://, empty for null or none."""
    at = F.locate("://", url)
    return F.when(at > 0, F.substring(url, at + 3, F.length(url))).otherwise(F.lit(""))


def host(url: Column) -> Column:
    return F.translate(F.regexp_extract(_after_scheme(url), r"^[^/?#]*", 0), UPPER, LOWER)


def path(url: Column) -> Column:
    return F.regexp_extract(_after_scheme(url), r"^[^/?#]*([^?#]*)", 1)


def normal_form(url: Column) -> Column:
    """Alias key of a url; null without a host."""
    name = F.regexp_replace(host(url), r"^(www|m)\.", "")
    return F.when(name != "", F.concat(name, F.regexp_replace(path(url), r"(/|\.html)$", "")))


def resolved(target: Column, base: Column) -> Column:
    """Target of a link in the page at base, as a url with ://; null for an empty one or another kind of scheme."""
    plain = F.regexp_extract(target, r"^[^?#]*", 0)
    folder = F.concat(F.lit("/"), F.regexp_extract(path(base), r"^/(.*/)?[^/]*$", 1))
    whole = F.when(plain == "", path(base)).when(plain.startswith("/"), plain).otherwise(F.concat(folder, plain))
    above = lambda kept: F.slice(kept, F.lit(1), F.greatest(F.size(kept) - 1, F.lit(1)))
    steps = F.aggregate(F.split(whole, "/"), F.array().cast("array<string>"), lambda kept, x: F.when(x == "..", above(kept)).when(x == ".", kept).otherwise(F.concat(kept, F.array(x))))
    local = F.concat(F.lit("x://"), host(base), F.array_join(steps, "/"))
    scheme = "^[A-Za-z][A-Za-z0-9+.-]*:"
    return F.when(target.rlike(scheme + "//"), target).when(target.startswith("//"), F.concat(F.lit("x:"), target)).when((target != "") & ~target.rlike(scheme), local)


def rule_of(name: Column, where: Column, rules: list[tuple[str, str, str]]) -> Column:
    """Struct (length, allows, rule, verdict) of the longest rule that fits, null without one; of equal ones an allowing one."""
    if len(rules) > RULES_MOST:
        raise ValueError(f"{len(rules)} rules; at most {RULES_MOST} can be part of a plan")
    fits = lambda h, p: ((name == h) | name.endswith("." + h)) & where.startswith(p)
    one = lambda h, p, v: F.struct(F.lit(len(h) + len(p)).alias("length"), F.lit(v == "allow").alias("allows"), F.lit(h + p).alias("rule"), F.lit(v).alias("verdict"))
    return F.array_max(F.filter(F.array(*(F.when(fits(h, p), one(h, p, v)) for h, p, v in rules)), lambda x: x.isNotNull())) if rules else F.lit(None).cast("struct<length:int,allows:boolean,rule:string,verdict:string>")


def page_links(pages: DataFrame) -> DataFrame:
    """a, b: normal forms of a page's url and of each of its canonical links and redirect targets, where these differ."""
    html = F.col("html")
    canonical = F.regexp_extract_all(html, F.lit(r"""(?i)<link\b[^>]*\brel=["']?canonical["']?[^>]*>"""), F.lit(0))
    refresh = F.regexp_extract_all(html, F.lit(r"""(?i)<meta\b[^>]*\bhttp-equiv=["']?refresh["']?[^>]*>"""), F.lit(0))
    href = F.transform(canonical, lambda x: F.regexp_extract(x, r"""(?i)\bhref=["']?([^"'\s>]+)""", 1))
    to = F.concat(href, F.transform(refresh, lambda x: F.regexp_extract(x, r"""(?i)\burl=["']?([^"'\s>]+)""", 1)))
    hinted = pages.where(html.rlike("(?i)canonical|http-equiv"))
    targets = hinted.select("url", F.explode(to).alias("to"))
    return targets.select(normal_form(F.col("url")).alias("a"), normal_form(resolved(F.col("to"), F.col("url"))).alias("b")).where("a <> b")


def judge(pages: DataFrame, rules: list[tuple[str, str, str]] = RULES, links: DataFrame | None = None) -> DataFrame:
    """page_id, host, path, rule, verdict, source of the verdict (rule, alias or default).

    links: more alias pairs as columns a and b of urls, such as logged redirects.
    """
    tied = page_links(pages)
    if links is not None:
        tied = tied.union(links.select(normal_form(F.col("a")).alias("a"), normal_form(F.col("b")).alias("b")).where("a <> b"))
    parsed = pages.select("page_id", host(F.col("url")).alias("host"), path(F.col("url")).alias("path"), normal_form(F.col("url")).alias("form"))
    ruled = parsed.withColumn("own", rule_of(F.col("host"), F.col("path"), rules))
    classes = components(cut(tied.distinct())).select(F.col("id").alias("form"), "component")
    forms = ruled.where("form is not null and own is not null").groupBy("form").agg(F.max("own.allows").alias("allowed"))
    by_class = forms.join(classes, "form", "left").groupBy(F.coalesce("component", "form").alias("component")).agg(F.max("allowed").alias("allowed"))
    decided = classes.join(by_class, "component").select("form", "allowed").union(forms.join(classes, "form", "left_anti").select("form", "allowed"))
    verdict = F.coalesce("own.verdict", F.when(F.col("allowed"), "allow").when(~F.col("allowed"), "block"), F.lit("allow"))
    decider = F.when(F.col("own").isNotNull(), "rule").when(F.col("allowed").isNotNull(), "alias").otherwise("default")
    return ruled.join(decided, "form", "left").select("page_id", "host", "path", F.col("own.rule").alias("rule"), verdict.alias("verdict"), decider.alias("decided_by"))
