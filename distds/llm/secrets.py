"""Secret scan: base patterns, plus weak credential parts that are reported only where complementary parts stand nearby.

Each pattern passes over a text once and sets its matches between marks; the pieces between marks give every place by sums of
lengths. Patterns that need a certain word, sign or long run are skipped for texts without it.

Parts of a document are laid out on its code points; two are near if at most ``scope`` code points lie between the end of one
and the start of the other, or if they overlap. For this interval join of access identifiers, secrets and endpoints each part
is a point at its start and a question ``scope`` after its end: of the parts begun by then, does the furthest end come to
within ``scope`` of the start? A weak identifier needs a secret nearby, a weak key needs an identifier, and an endpoint needs
both. Weak parts inside strong ones are found the same way and left out first. All of it is linear in the matches of a text
but for sorting.

Edge cases: a null text is empty; long texts and texts of very many matches are scanned whole; repeated rows give equal rows; an
empty table gives no rows; other columns are ignored. Plain DataFrame operations throughout.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from distds.llm.scratch import only

#: The kinds in the order of reports, each with its pattern (letters of names in either case).
KINDS = ("assign", "access", "hex", "ident", "key", "endpoint")
PATTERNS = {
    "assign": r"""(?:[Pp][Aa][Ss][Ss][Ww][Oo][Rr][Dd]|[Pp][Aa][Ss][Ss][Ww][Dd]|[Ss][Ee][Cc][Rr][Ee][Tt]|[Tt][Oo][Kk][Ee][Nn]|[Aa][Pp][Ii]_?[Kk][Ee][Yy])["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""",
    "access": r"(AKIA[A-Z0-9]+)",
    "hex": r"([0-9a-f]{32,})",
    "ident": r"""(?:[Uu][Ss][Ee][Rr][Nn][Aa][Mm][Ee]|[Uu][Ss][Ee][Rr]|[Cc][Ll][Ii][Ee][Nn][Tt]_[Ii][Dd]|[Aa][Cc][Cc][Oo][Uu][Nn][Tt]|[Ll][Oo][Gg][Ii][Nn])["']?\x20*[:=]\x20*["']?([A-Za-z0-9@_.-]+)""",
    "key": r"([A-Za-z0-9+/_-]{20,})",
    "endpoint": r"((?:https?|ftp|postgres|mysql|mongodb|redis|amqp)://[A-Za-z0-9._~:@%-]+)",
}
#: The least length of the pattern's group.
LEAST = {"assign": 8, "access": 16, "hex": 32, "ident": 4, "key": 20, "endpoint": 10}
#: Letters (lower case) of which one must stand in a text for the kind to match; runs must hold 20 signs of a key.
HINTS = {"assign": ("passw", "secret", "token", "key"), "ident": ("user", "cl", "account", "log")}
RUN = r"(?<![A-Za-z0-9+/_-])[A-Za-z0-9+/_-]{20}"
BLOCK = 256
MARK, STAND_IN = "\x00", "\x01"
SPANS = "array<struct<k:int,s:int,e:int>>"


def let(value: Column, body: Callable[[Column], Column]) -> Column:
    """``body`` of a value that is worked out once, however often the body names it."""
    return F.element_at(F.transform(F.array(value), body), 1)


def total(a: Column) -> Column:
    return F.aggregate(a, F.lit(0), lambda acc, x: acc + x)


def sums_before(lengths: Column) -> Column:
    """For an array of numbers, the sum of those before each. Sums of blocks come first: an element costs half a block, and
    blocks cost half their number each, which is little for up to millions of elements."""

    def inside(a: Column) -> Column:
        return F.transform(a, lambda _, j: total(F.slice(a, F.lit(1), j)))

    ids = F.sequence(F.lit(0), F.floor((F.size(lengths) - 1) / BLOCK).cast("int"))
    cut = F.transform(ids, lambda i: F.slice(lengths, i * BLOCK + 1, F.lit(BLOCK)))

    def joined(blocks: Column) -> Column:
        heads = let(F.transform(blocks, total), inside)
        return F.flatten(F.zip_with(blocks, heads, lambda b, h: F.transform(b, lambda _, j: h + total(F.slice(b, F.lit(1), j)))))

    return F.when(F.size(lengths) > 0, let(cut, joined)).otherwise(F.array().cast("array<int>"))


def hint(text: Column, low: Column, kind: str) -> Column:
    """Whether a text can hold the kind at all, from plain searches."""
    if kind == "access":
        return F.contains(text, F.lit("AKIA"))
    if kind == "endpoint":
        return F.contains(text, F.lit("://"))
    if kind in HINTS:
        seen = F.lit(False)
        for word in HINTS[kind]:
            seen = seen | F.contains(low, F.lit(word))
        return seen
    return text.rlike(RUN)


def spans(text: Column, kind: str) -> Column:
    """array<struct<k,s,e>>: the matches of a kind, in code points; what fails its length is dropped after matching.

    ``text`` must not hold MARK. Of the pieces between marks every third one is a gap, then come a match and its value.
    """
    marked = F.regexp_replace(text, F.lit("(" + PATTERNS[kind] + ")"), F.lit(f"{MARK}$1{MARK}$2{MARK}"))

    def laid_out(pieces: Column) -> Column:
        ids = F.sequence(F.lit(0), F.floor((F.size(pieces) - 4) / 3).cast("int"))
        both = F.transform(ids, lambda i: F.struct(F.length(pieces[i * 3]).alias("g"), F.length(pieces[i * 3 + 1]).alias("n"), pieces[i * 3 + 2].alias("t")))
        return let(both, placed)

    def placed(both: Column) -> Column:
        at = F.zip_with(both, let(F.transform(both, lambda x: x["g"] + x["n"]), sums_before), lambda x, s: F.struct((s + x["g"]).alias("s"), (s + x["g"] + x["n"]).alias("e"), x["t"].alias("t")))
        ok = F.filter(at, lambda x: (F.length(x["t"]) >= LEAST[kind]) & (F.lit(True) if kind != "key" else x["t"].rlike("[0-9]") & x["t"].rlike("[A-Za-z]")))
        return F.transform(ok, lambda x: F.struct(F.lit(KINDS.index(kind)).alias("k"), x["s"].alias("s"), x["e"].alias("e")))

    none = F.array().cast(SPANS)
    return let(marked, lambda m: F.when(F.contains(m, F.lit(MARK)), let(F.split(m, MARK, -1), laid_out)).otherwise(none))


def report(parts: Column) -> Column:
    """kind:start:end by start and kind, comma-joined."""
    names = F.array(*[F.lit(k) for k in KINDS])
    order = F.array_sort(F.transform(parts, lambda x: F.struct(x["s"].alias("s"), x["k"].alias("k"), x["e"].alias("e"))))
    return F.array_join(F.transform(order, lambda x: F.concat_ws(":", F.element_at(names, x["k"] + 1), x["s"].cast("string"), x["e"].cast("string"))), ",")


def furthest(scope: Column, kinds: tuple[int, ...]) -> Column:
    """The furthest end of parts of some kinds that have begun by a point; points hold ``p`` and parts ask by ``p.asks``."""
    begun = Window.partitionBy("r1", "r2").orderBy("p.at").rangeBetween(Window.unboundedPreceding, Window.currentRow)
    end = F.max(F.when(~F.col("p.asks") & F.col("k").isin(*kinds), F.col("e"))).over(begun)
    return F.coalesce(end >= F.col("s") - scope, F.lit(False))


def points(parts: DataFrame, until: Column) -> DataFrame:
    """Two rows for each part: its start, and the place ``until`` which it looks back from."""
    start = F.struct(F.col("s").alias("at"), F.lit(False).alias("asks"))
    return parts.withColumn("p", F.explode(F.array(start, F.struct(until.alias("at"), F.lit(True).alias("asks")))))


def scan_secrets(docs: DataFrame, scratch, scope: int = 300) -> DataFrame:
    """doc_id, n_assign, n_access, n_hex, base_sha256, spans, n_linked for every row of ``docs``."""
    docs = only(docs, "doc_id", "text")
    text = F.coalesce(F.col("text"), F.lit(""))
    safe, none = F.replace(text, F.lit(MARK), F.lit(STAND_IN)), F.array().cast(SPANS)
    hints = docs.select("doc_id", safe.alias("t"), F.lower(text).alias("low"), F.xxhash64("doc_id", text).alias("r1"), F.xxhash64(text, "doc_id").alias("r2"))
    found = {k: F.when(hint(F.col("t"), F.col("low"), k), spans(F.col("t"), k)).otherwise(none) for k in KINDS if k not in ("hex", "key")}
    runs = F.when(hint(F.col("t"), F.col("low"), "key"), F.struct(spans(F.col("t"), "hex").alias("hex"), spans(F.col("t"), "key").alias("key")))
    base = hints.select("doc_id", "r1", "r2", *[c.alias(k) for k, c in found.items()], runs.alias("runs"))
    base = scratch.stash(base.select("doc_id", "r1", "r2", *[F.coalesce(f"runs.{k}", none).alias(k) if k in ("hex", "key") else F.col(k) for k in KINDS]))
    strong, weak = F.concat("assign", "access", "hex"), F.concat("ident", "key", "endpoint")
    parts = base.filter(F.size(weak) > 0).filter((F.size("access") + F.size("ident") > 0) & (F.size("assign") + F.size("hex") + F.size("key") > 0))
    parts = parts.select("r1", "r2", F.explode(F.concat(strong, weak)).alias("x")).select("r1", "r2", "x.*")
    covered = furthest(F.lit(-1), (0, 1, 2))
    parts = points(parts, F.col("e") - 1).withColumn("covered", covered).filter(F.col("p.asks") & ((F.col("k") < 3) | ~F.col("covered"))).drop("p", "covered")
    near = points(parts, F.col("e") + scope).withColumn("who", furthest(F.lit(scope), (1, 3))).withColumn("what", furthest(F.lit(scope), (0, 2, 4))).filter("p.asks")
    joined = ((F.col("k") == 3) & F.col("what")) | ((F.col("k") == 4) & F.col("who")) | ((F.col("k") == 5) & F.col("who") & F.col("what"))
    linked = near.filter(joined).groupBy("r1", "r2").agg(F.collect_set(F.struct("k", "s", "e")).alias("linked"))  # some matches of one text
    rows = base.join(linked, ["r1", "r2"], "left")
    extra = F.coalesce("linked", none)
    return rows.select(
        "doc_id", F.size("assign").cast("long").alias("n_assign"), F.size("access").cast("long").alias("n_access"), F.size("hex").cast("long").alias("n_hex"),
        F.sha2(report(strong), 256).alias("base_sha256"), report(F.concat(strong, extra)).alias("spans"), F.size(extra).cast("long").alias("n_linked"),
    )
