"""Secret scans with corpus-wide ownership frequency, in DataFrame functions only.

Three base patterns give spans in every text; a fourth finds other opaque tokens (a digit, a letter, 16 or more
characters).  The values found are hashed and counted over the whole corpus by distinct repository (source and
language) and owner (source).  A value that COPIED_OWNERS owners share, or two owners in COPIED_REPOSITORIES
repositories, is a widely copied example; any other is owner-specific and looks live, in however many repositories
its one owner keeps it.  Opaque tokens that look live and lie outside the base spans are added.

A text gives the lengths between its matches and the matches; positions are running sums over these as rows, so the
time is linear in the text and in its matches.

Defined results: a null text counts as empty; null owners and languages count as one owner named ''; texts of any
length are scanned whole; ties in position keep the order of KINDS; repeated rows are scanned alike and count once
for ownership; an empty table gives an empty table.  Input columns other than those named are ignored.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from momenttree.llm.runtime import cut

#: Name, pattern, group that holds the secret, its least length.
KINDS = [
    ("assign", r"""(?i:(password|passwd|secret|token|api_?key))["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", 2, 6),
    ("access", r"AKIA[A-Z0-9]+", 0, 20),
    ("hex", r"[0-9a-f]+", 0, 24),
]
OPAQUE = ("opaque", r"[A-Za-z0-9+/_-]+", 0, 16)
#: The same matches, those that are too short left out: no other match begins inside one of these.
LONG = {
    "access": r"AKIA[A-Z0-9]{16,}",
    "hex": r"[0-9a-f]{24,}",
    "opaque": r"(?<![A-Za-z0-9+/_-])(?=[A-Za-z0-9+/_-]{16})(?=[A-Za-z+/_-]*[0-9])(?=[0-9+/_-]*[A-Za-z])[A-Za-z0-9+/_-]++",
}
#: For each kind, what any of its matches contains; texts without it are not scanned for that kind.
HINTS = {"assign": r"[:=]\x20*[\"']?[A-Za-z0-9+/_.=-]{6}", "access": "AKIA[A-Z0-9]{16}", "hex": "[0-9a-f]{24}", "opaque": r"[0-9]"}
COPIED_OWNERS = 3
COPIED_REPOSITORIES = 6
MASK = "[secret]"
#: Characters of a text that are masked together.
BLOCK = 4_096


def _matches(text: Column, rank: int, kind: str, pattern: str) -> Column:
    """Struct (rank, gaps: lengths of what lies before, between and after the matches, hits), null without any."""
    pattern = LONG.get(kind, pattern)
    gaps = F.transform(F.split(text, pattern, -1), F.length)
    return F.when(text.rlike(HINTS[kind]), F.struct(F.lit(rank).alias("rank"), gaps.alias("gaps"), F.regexp_extract_all(text, F.lit(pattern), F.lit(0)).alias("hits")))


def scan(docs: DataFrame, *, kept: tuple[str, ...] = ()) -> DataFrame:
    """row (a fresh key), doc_id, owner, repository, matches of each kind, and the kept columns, of every row of docs."""
    column = lambda c: F.coalesce(F.col(c).cast("string"), F.lit("")) if c in docs.columns else F.lit("")
    found = F.array(*(_matches(F.col("scanned"), k, kind, pattern) for k, (kind, pattern, _, _) in enumerate([*KINDS, OPAQUE])))
    chosen = docs.select(F.col("doc_id").cast("bigint").alias("doc_id"), column("text").alias("scanned"), column("source").alias("owner"), column("lang").alias("lang"), *(F.col(c).alias(f"kept_{c}") for c in kept))
    return chosen.select(
        F.monotonically_increasing_id().alias("row"), "doc_id", "owner", F.concat_ws("/", "owner", "lang").alias("repository"),
        F.filter(found, lambda m: F.size(m["hits"]) > 0).alias("matches"), *(f"kept_{c}" for c in kept),
    )


def spans(found: DataFrame) -> DataFrame:
    """row, owner, repository, start, end, rank, is_base, outside, value (hash) of every span of a cut scan.

    outside: the span overlaps no base span.  Spans stand in order of start, base ones first, so the largest end of the
    base spans before and the nearest start after decide.
    """
    each = found.select("row", "owner", "repository", F.explode("matches").alias("m")).select("row", "owner", "repository", "m.rank", F.posexplode(F.arrays_zip("m.gaps", "m.hits")).alias("pos", "h"))
    secret = F.when(F.col("rank") == 0, F.regexp_extract("h.hits", KINDS[0][1], KINDS[0][2])).otherwise(F.col("h.hits"))
    within = Window.partitionBy("row", "rank").orderBy("pos")
    length = F.coalesce(F.length("h.hits"), F.lit(0))
    placed = each.repartition("row").withColumn("end", F.sum(F.col("h.gaps") + length).over(within)).where("h.hits is not null")
    long = placed.select("row", "owner", "repository", (F.col("end") - length).alias("start"), "end", "rank", secret.alias("secret"), (F.col("rank") < len(KINDS)).alias("is_base"))
    long = long.where((F.col("rank") > 0) | (F.length("secret") >= KINDS[0][3]))
    forward, backward = Window.partitionBy("row").orderBy("start", "rank"), Window.partitionBy("row").orderBy(F.desc("start"), F.desc("rank"))
    before = F.max(F.when(F.col("is_base"), F.col("end"))).over(forward.rowsBetween(Window.unboundedPreceding, -1))
    after = F.min(F.when(F.col("is_base"), F.col("start"))).over(backward.rowsBetween(Window.unboundedPreceding, -1))
    outside = (F.coalesce(before, F.lit(0)) <= F.col("start")) & (F.coalesce(after, F.col("end")) >= F.col("end"))
    return long.withColumn("outside", outside).withColumn("value", F.sha2(F.col("secret").cast("binary"), 256)).drop("secret")


def ownership(found: DataFrame) -> DataFrame:
    """value, n_repositories, n_owners, copied, over all spans."""
    by_owner = found.select("value", "repository", "owner").distinct().groupBy("value", "owner").agg(F.count("*").alias("repositories"))
    counted = by_owner.groupBy("value").agg(F.sum("repositories").alias("n_repositories"), F.count("*").alias("n_owners"))
    return counted.withColumn("copied", (F.col("n_owners") >= COPIED_OWNERS) | ((F.col("n_owners") == 2) & (F.col("n_repositories") >= COPIED_REPOSITORIES)))


def decided(found: DataFrame) -> DataFrame:
    """row, start, end, rank, is_base, live: base spans, and opaque ones that look live and lie outside them; found is a cut scan."""
    all_spans = cut(spans(found.where("size(matches) > 0")))
    judged = all_spans.join(ownership(all_spans).select("value", "copied"), "value")
    return judged.where("is_base or (outside and not copied)").select("row", "start", "end", "rank", "is_base", (~F.col("copied")).alias("live"))


def report(docs: DataFrame) -> DataFrame:
    """doc_id, n_assign, n_access, n_hex, base_sha256, spans, n_added, n_live (base and added spans that look live)."""
    found = cut(scan(docs))
    names = F.array(*(F.lit(k[0]) for k in [*KINDS, OPAQUE]))
    span = F.struct("start", "rank", F.concat_ws(":", F.get(names, F.col("rank")), "start", "end").alias("said"), "is_base")
    count = lambda rank: F.count_if(F.col("rank") == rank).alias(f"n_{KINDS[rank][0]}")
    by_row = decided(found).groupBy("row").agg(*map(count, range(len(KINDS))), F.array_sort(F.collect_list(span)).alias("all"), F.count_if(~F.col("is_base")).cast("int").alias("n_added"), F.count_if("live").cast("int").alias("n_live"))
    said = lambda chosen: F.array_join(F.transform(chosen, lambda s: s["said"]), ",")
    joined = found.select("row", "doc_id").join(by_row, "row", "left").na.fill(0, [f"n_{k[0]}" for k in KINDS] + ["n_added", "n_live"])
    base = F.coalesce(said(F.filter("all", lambda s: s["is_base"])), F.lit(""))
    return joined.select("doc_id", *(f"n_{k[0]}" for k in KINDS), F.sha2(base.cast("binary"), 256).alias("base_sha256"), F.coalesce(said(F.col("all")), F.lit("")).alias("spans"), "n_added", "n_live")


def _masked(texts: DataFrame, live: DataFrame) -> DataFrame:
    """row, redacted of the rows (row, text) that live spans (row, start, end) touch; spans that overlap have one mask.

    Texts are cut into blocks of BLOCK characters, each masked on its own, so no step copies a whole text for each span.
    """
    order = Window.partitionBy("row").orderBy("start", "end")
    reach = F.max("end").over(order.rowsBetween(Window.unboundedPreceding, -1))
    parts = live.withColumn("fresh", F.coalesce(reach <= F.col("start"), F.lit(True)).cast("int")).withColumn("part", F.sum("fresh").over(order.rowsBetween(Window.unboundedPreceding, 0)))
    merged = parts.groupBy("row", "part").agg(F.min("start").alias("start"), F.max("end").alias("end"))
    touched = merged.select("row", "start", "end", F.explode(F.sequence(*(F.floor(c / BLOCK).cast("int") for c in (F.col("start"), F.col("end") - 1)))).alias("block"))
    of_block = touched.groupBy("row", "block").agg(F.array_sort(F.collect_list(F.struct("start", "end"))).alias("spans"))
    cut_up = texts.join(live.select("row").distinct(), "row", "left_semi").select("row", F.posexplode(F.regexp_extract_all("text", F.lit(f"(?s).{{1,{BLOCK}}}"), F.lit(0))).alias("block", "piece"))
    base = F.col("block") * F.lit(BLOCK)

    def step(acc, s):
        a, z = F.greatest(s["start"] - base, F.lit(0)).cast("int"), F.least(s["end"] - base, F.lit(BLOCK)).cast("int")
        gap = F.substring(F.col("piece"), acc["at"] + 1, a - acc["at"])
        return F.struct(z.alias("at"), F.concat(acc["out"], gap, F.when(s["start"] >= base, MASK).otherwise("")).alias("out"))

    start = F.struct(F.lit(0).alias("at"), F.lit("").alias("out"))
    whole = F.aggregate("spans", start, step, lambda acc: F.concat(acc["out"], F.substring(F.col("piece"), acc["at"] + 1, F.lit(BLOCK))))
    changed = cut_up.join(of_block, ["row", "block"], "left").select("row", "block", F.coalesce(whole, "piece").alias("piece"))
    pieces = F.transform(F.array_sort(F.collect_list(F.struct("block", "piece"))), lambda x: x["piece"])
    return changed.groupBy("row").agg(F.array_join(pieces, "").alias("redacted"))


def redact(docs: DataFrame) -> DataFrame:
    """docs with every live-looking span replaced by MASK and n_chars set anew; widely copied examples stay.

    Rows without any match go straight through; only the few others are written and joined.
    """
    columns = docs.columns
    found = scan(docs, kept=tuple(columns))
    plain = found.where("size(matches) = 0").select(*(F.col(f"kept_{c}").alias(c) for c in columns))
    marked = cut(found.where("size(matches) > 0"))
    live = decided(marked).where("live").select("row", "start", "end")
    changed = marked.join(_masked(marked.select("row", F.col("kept_text").cast("string").alias("text")), cut(live)), "row", "left")
    new = {"text": F.coalesce("redacted", "kept_text")}
    if "n_chars" in columns:
        new["n_chars"] = F.when(F.col("redacted").isNotNull(), F.length("redacted")).otherwise(F.col("kept_n_chars")).cast(docs.schema["n_chars"].dataType)
    return plain.select(columns).union(changed.select(*(new.get(c, F.col(f"kept_{c}")).alias(c) for c in columns)))
