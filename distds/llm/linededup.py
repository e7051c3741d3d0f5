"""Line dedup by site-relative frequency: a line that stands on too large a share of a host's pages is boilerplate and goes.

A page is no witness against itself: a line's share is taken over the other pages of its host, (n - 1) of (pages - 1). So one
rule holds for hosts of any size, and the only page of a host has nothing to lose.

Counts by (host, line) are summed before they move. Boilerplate lines of a host number at most its lines per page divided by
the ratio, so they travel as one array for each host; a page looks its own lines up in it.

Edge cases: null texts stay null; pages without a host form a host of their own; blank lines are never counted or dropped;
repeated rows count as pages; extra columns are kept; an empty table gives no rows. Lines are compared by a 64-bit hash of line
and host.

With ``once`` copies have no weight of their own: equal texts of a host count as one page, and pages that consist of frequent
lines by half or more (near copies of each other, as a rule) have one vote for a line together. What only they share stays. A
page that would lose every line stays whole, so some copy of each text is left to a later stage.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from distds.llm.scratch import Scratch, fresh

RATIO = 0.1


def keys(lines: Column, host: Column) -> Column:
    return F.transform(lines, lambda x: F.when(F.length(F.trim(x)) > 0, F.xxhash64(F.trim(x), host)))


def boilerplate(seen: DataFrame, pages: DataFrame, ratio: float) -> DataFrame:
    """h, boiler: of ``seen`` (h, k, n) the lines on too large a share of the host's other pages."""
    over = seen.join(pages, "h").filter(F.col("n") - 1 > (F.col("pages") - 1) * F.lit(ratio))
    return over.groupBy("h").agg(F.collect_set("k").alias("boiler"))


def often_by_page(scratch: Scratch, rows: DataFrame, k: Column, ratio: float) -> DataFrame:
    """h, boiler by pages."""
    pages = scratch.stash(rows.groupBy("h").agg(F.count("*").alias("pages")))
    return boilerplate(rows.select("h", F.explode(F.array_distinct(F.array_compact(k))).alias("k")).groupBy("h", "k").agg(F.count("*").alias("n")), pages, ratio)


def often_by_text(scratch: Scratch, rows: DataFrame, text: Column, ratio: float) -> DataFrame:
    """h, boiler: the same over distinct texts, of which those made of frequent lines by half have one vote together."""
    text = F.coalesce(text, F.lit(""))
    lines = F.split(text, "\n", -1)
    sized = F.arrays_zip(keys(lines, F.col("h")).alias("k"), F.transform(lines, lambda x: F.length(F.trim(x))).alias("n"))
    sized = F.array_distinct(F.filter(sized, lambda x: x["k"].isNotNull()))
    texts = scratch.stash(rows.select("h", F.xxhash64(text).alias("t"), sized.alias("ls")).groupBy("h", "t").agg(F.first("ls").alias("ls")))
    pages = scratch.stash(texts.groupBy("h").agg(F.count("*").alias("pages")))
    first = scratch.stash(boilerplate(texts.select("h", F.explode("ls.k").alias("k")).groupBy("h", "k").agg(F.count("*").alias("n")), pages, ratio))
    marked = texts.join(first, "h").withColumn("hit", F.array_intersect("ls.k", "boiler")).filter(F.size("hit") > 0)

    def total(a: Column) -> Column:
        return F.aggregate(a, F.lit(0), lambda acc, x: acc + x["n"])

    gone = total(F.filter("ls", lambda x: F.array_contains("hit", x["k"])))
    votes = marked.select("h", (2 * gone >= total(F.col("ls"))).cast("int").alias("heavy"), F.explode("hit").alias("k"))
    return boilerplate(votes.groupBy("h", "k").agg((F.sum(1 - F.col("heavy")) + F.max("heavy")).alias("n")), pages, ratio)


def dedup_lines(docs: DataFrame, host: Column, text: str = "text", ratio: float = RATIO, count: bool = False, once: bool = False) -> DataFrame:
    """``docs`` with ``text`` cleaned; with ``count`` also n_lines and n_dropped. Lines end at newlines."""
    scratch = Scratch(docs.sparkSession)
    names, at = docs.columns, docs.columns.index(text)
    own = [f"c{i}" for i in range(len(names))]  # names may clash in case
    rows = docs.withColumn(fresh(docs, "_host"), F.coalesce(host.cast("string"), F.lit(""))).toDF(*own, "h")
    text = F.col(own[at])
    lines = F.split(text, "\n", -1)
    k = keys(lines, F.col("h"))
    often = often_by_text(scratch, rows, text, ratio) if once else often_by_page(scratch, rows, k, ratio)
    rows = rows.join(scratch.stash(often), "h", "left")
    rows = rows.withColumn("hit", F.when(F.col("boiler").isNull(), F.array().cast("array<bigint>")).otherwise(F.array_intersect(F.array_compact(k), "boiler")))
    if once:
        rows = rows.withColumn("hit", F.when(F.exists(k, lambda x: ~F.array_contains("hit", x)), F.col("hit")).otherwise(F.array().cast("array<bigint>")))
    kept = F.filter(F.arrays_zip(lines.alias("l"), k.alias("k")), lambda x: ~F.coalesce(F.array_contains("hit", x["k"]), F.lit(False)))
    clean = F.when(F.size("hit") > 0, F.array_join(F.transform(kept, lambda x: x["l"]), "\n")).otherwise(text)
    out = [clean.alias(c) if i == at else F.col(c) for i, c in enumerate(own)]
    if count:
        n = F.when(text.isNull(), 0).otherwise(F.size(lines))
        out += [n.cast("long").alias("n_lines"), F.when(F.size("hit") > 0, n - F.size(kept)).otherwise(0).cast("long").alias("n_dropped")]
        names = [*names, "n_lines", "n_dropped"]
    return rows.select(*out).toDF(*names)


ENTITIES = (("&lt;", "<"), ("&gt;", ">"), ("&quot;", '"'), ("&amp;", "&"))


def page_text(html: Column) -> Column:
    """Text of a page, one line for each block element; scripts, styles and comments go."""
    t = F.regexp_replace(html, r"(?is)<(?:script\b.*?</script>|style\b.*?</style>|!--.*?-->)", "")
    t = F.regexp_replace(t, r"(?i)</?(?:br|p|div|li|h[1-6]|tr|title|article|nav|ul|ol|table)\b[^>]*>", "\n")
    t = F.regexp_replace(t, r"<[^>]*>", "")
    for a, b in ENTITIES:
        t = F.replace(t, F.lit(a), F.lit(b))
    return F.array_join(F.filter(F.transform(F.split(t, "\n", -1), lambda x: F.trim(x)), lambda x: x != ""), "\n")


def host_of(url: Column) -> Column:
    return F.lower(F.regexp_extract(url, r"^[A-Za-z][A-Za-z0-9+.-]*://([^/?#]*)", 1))
