"""N-gram Jaccard join by prefix filters under several global token orders, and the groups that its links make.

1. Every text becomes a set of shingle hashes; equal sets become one node. A fixed share of the hash range (the *region*,
   a third more than the prefix needs on average) is emitted; a set too small to fill its prefix from there adds its next hashes.
2. Sets that hold a region token are counted over all nodes. Tokens of one node come first in every order and match nothing,
   so only tokens of two or more nodes are sent back.
3. The orders rank region tokens by count (or its logarithm) and differ in how ties fall. Two sets similar enough share a
   prefix token under each order, so a pair is a candidate only if it meets under all of them. This holds for lists of any
   length: pairs of short lists (up to ``SHORT`` nodes) are filtered as they are listed, others where their sets meet.
4. Long lists are first compared with representatives: every node with one node of the list, then in a few more rounds those
   not yet linked with one node of the list's largest group. Work grows with the list, and most groups of near copies are whole
   after a round or two; a list whose nodes are all in one group is done.
5. What is left becomes blocks of suspects: groups that a short list's pair or an unfinished list joins. In a block, nodes
   outside the largest group meet each other and those of the largest group, by size band and hash in cells of bounded size.
6. A cell looks for candidates among its nodes, verifies only these by exact sets, and skips nodes of one group. It emits edges
   of a spanning forest; components of all edges are the groups.

Edge cases: null and empty texts have no set and link with nothing; texts with fewer words than a shingle are one shingle;
repeated rows and ties share a node; null doc_ids are allowed (the smallest non-null one names a group); an empty table gives
no rows; other columns are ignored. Sets are told apart by 128-bit digests; nodes are their first halves, and where two sets
share one, all but one of them get another number.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from distds.llm import screen
from distds.llm import textkernels as tk
from distds.llm.components import components
from distds.llm.scratch import Scratch, bucket_count, only

#: Pairs are listed for prefix lists up to this long: their number is linear in the list entries.
SHORT = 32
#: Sets and tokens in a cell, each side. A set goes to every cell of its chunk, so what moves grows with the number of chunks:
#: tokens bound a cell's memory, and sets only the cells of small sets. Partners of a representative in a cell.
CELL, CELL_TOKENS, PARTNERS = 8192, 500_000, 512
#: Candidates of a node in a cell above which they are counted together.
MANY = 16
#: Rounds in which long lists meet representatives, at most.
ROUNDS = 4
SETS = "doc_id long, row long, row2 long, n int, sig long, sig2 long, entries array<long>"
FULL = "sig long, sig2 long, tokens array<long>"
LINKS = "a long, b long, checked long"


def prefix_length(n, num: int, den: int):
    return n - (n * num + den - 1) // den + 1


def tokenise(batches, k: int, num: int, den: int, region: float):
    limit = np.uint64(int(region * 2.0**64))
    for batch in batches:
        ns, sigs, entries = [], [], []
        for first, run in tk.runs_of(batch.column("text")):
            for s in tk.shingle_sets(run, k):
                n = len(s)
                ns.append(n)
                sigs.append(tk.digest(s) if n else (None, None))
                entries.append(s[: max(int(np.searchsorted(s, limit)), prefix_length(n, num, den))].view(np.int64) if n else None)
        offs = np.cumsum([0] + [0 if e is None else len(e) for e in entries]).astype(np.int32)
        flat = np.concatenate([e for e in entries if e is not None] or [np.zeros(0, np.int64)])
        yield pa.RecordBatch.from_arrays([batch.column("doc_id"), batch.column("row"), batch.column("row2"), pa.array(ns, pa.int32()), *(pa.array([x[i] for x in sigs], pa.int64()) for i in (0, 1)), pa.ListArray.from_arrays(pa.array(offs), pa.array(flat))], names=["doc_id", "row", "row2", "n", "sig", "sig2", "entries"])


def full_sets(batches, k: int, wanted: list[bytes] | None = None):
    """Digest and tokens of texts; with filters of wanted rows, of those that may be among them."""
    for batch in batches:
        if wanted is not None:
            batch = batch.filter(pa.array(screen.maybe(wanted, batch.column("row").to_numpy())))
        for _, run in tk.runs_of(batch.column("text")):
            sets = [s for s in tk.shingle_sets(run, k) if len(s)]
            offs = np.cumsum([0] + [len(s) for s in sets]).astype(np.int32)
            flat = np.concatenate(sets).view(np.int64) if sets else np.zeros(0, np.int64)
            halves = np.array([tk.digest(s) for s in sets], dtype=np.int64).reshape(-1, 2)
            yield pa.RecordBatch.from_arrays([pa.array(halves[:, 0]), pa.array(halves[:, 1]), pa.ListArray.from_arrays(pa.array(offs), pa.array(flat))], names=["sig", "sig2", "tokens"])


def suspect_sets(slim: DataFrame, members: DataFrame, k: int, most: int) -> DataFrame:
    """node, tokens, p1, p2, p3 of the sets in ``members`` (with row, sig, sig2): texts are screened by row where they lie, and the join by
    digests drops what else the screen lets through."""
    filters = screen.screen(members.select(F.col("row").alias("key")).distinct(), most)
    texts = slim.select("row", "text")
    if filters is None:
        texts = texts.join(members.select("row"), "row", "left_semi")
    sets = texts.mapInArrow(lambda it: full_sets(it, k, filters and filters.value), FULL)
    return sets.dropDuplicates(["sig", "sig2"]).join(members.select("sig", "sig2", "node", "p1", "p2", "p3"), ["sig", "sig2"]).select("node", "tokens", "p1", "p2", "p3")


def meeting(flat: np.ndarray, owner: np.ndarray, tokens: np.ndarray, m: int) -> np.ndarray:
    """How many of ``tokens`` each of ``m`` sets holds; ``flat`` and ``owner``: all their tokens, sorted."""
    lo, hi = np.searchsorted(flat, tokens, "left"), np.searchsorted(flat, tokens, "right")
    c = hi - lo
    at = np.repeat(lo - np.concatenate(([0], np.cumsum(c)[:-1])), c) + np.arange(int(c.sum()))
    return np.bincount(owner[at], minlength=m)


def posted(sets: list):
    """(tokens of all sets in order, the set of each)."""
    flat, owner = np.concatenate(sets), np.repeat(np.arange(len(sets)), [len(x) for x in sets])
    order = np.argsort(flat, kind="stable")
    return flat[order], owner[order]


def in_common(a: np.ndarray, b: np.ndarray) -> int:
    """Tokens that two sorted sets share."""
    a, b = (a, b) if len(a) <= len(b) else (b, a)
    return int((b[np.minimum(np.searchsorted(b, a), len(b) - 1)] == a).sum())


def linked_in_cell(nodes: np.ndarray, sides: np.ndarray, groups: np.ndarray, sets: list, prefixes: list, num: int, den: int):
    """(edges of a spanning forest of the links in a cell, pairs verified). Side 0 meets side 1; nodes of side 2 meet each other.

    Candidates share a token under each order (``prefixes``: for each order the tokens of each node). Nodes of one group, or
    already in one tree, are not compared.
    """
    m, checked, edges = len(nodes), 0, []
    sizes = np.array([len(s) for s in sets])
    root = np.unique(groups, return_inverse=True)[1].ravel()
    cross = bool((sides < 2).any())
    lists, whole = [(lanes, *posted(lanes)) for lanes in prefixes], None
    for i in np.argsort(-sizes, kind="stable"):
        if cross and sides[i] != 0:
            continue
        open_ = (root != root[i]) & ((sides == 1) if cross else True)
        open_ &= np.minimum(sizes, sizes[i]) * den >= np.maximum(sizes, sizes[i]) * num
        for lanes, flat, owner in lists:
            if not open_.any():
                break
            open_ &= meeting(flat, owner, lanes[i], m) > 0
        near = np.flatnonzero(open_)
        checked += len(near)
        if len(near) > MANY:  # one pass over all sets of the cell counts for all candidates
            whole = whole or posted(sets)
            common = meeting(*whole, sets[i], m)[near]
        else:
            common = np.array([in_common(sets[i], sets[j]) for j in near], dtype=np.int64)
        for j in near[common * den >= (sizes[i] + sizes[near] - common) * num]:
            if root[i] != root[j]:
                edges.append((nodes[i], nodes[j]))
                root[root == root[j]] = root[i]
    return edges, checked


def compare(table: pa.Table, num: int, den: int) -> pa.Table:
    """Edges of a cell, and one row with the number of pairs it verified."""
    edges, checked = [], 0
    if table.num_rows > 1:
        table = table.take(pc.sort_indices(table.column("node")))

        def lists(name: str) -> list:
            col = table.column(name).combine_chunks()
            offs, flat = col.offsets.to_numpy(), col.values.to_numpy()
            return [flat[offs[i] : offs[i + 1]].view(np.uint64) for i in range(len(offs) - 1)]

        node, side, group = (table.column(c).to_numpy() for c in ("node", "side", "comp"))
        edges, checked = linked_in_cell(node, side, group, lists("tokens"), [lists(p) for p in ("p1", "p2", "p3")], num, den)
    cols = [[int(a) for a, _ in edges] + [None], [int(b) for _, b in edges] + [None], [0] * len(edges) + [checked]]
    return pa.table({n: pa.array(c, pa.int64()) for n, c in zip(("a", "b", "checked"), cols)})


def prefix_arrays(df: DataFrame, num: int, den: int) -> DataFrame:
    """``df``: node, n, held, common array<struct<c,t>>. Adds the shared part of the prefix under each order."""
    n = F.col("n").cast("long")
    p = n - F.floor((n * num + den - 1) / den) + 1
    room = F.when(F.col("held") <= p, F.size("common")).otherwise(F.greatest(F.lit(0), (p - (F.col("held") - F.size("common"))).cast("int")))

    def under(rank) -> object:
        ranked = F.array_sort(F.transform("common", lambda x: F.struct(*rank(x), x["t"].alias("t"))))
        return F.transform(F.slice(ranked, F.lit(1), room), lambda x: x["t"])

    by_count = under(lambda x: [x["c"].alias("r")])
    by_log = under(lambda x: [F.floor(F.log2(x["c"])).alias("r"), F.hash(x["t"]).alias("h")])
    reverse = under(lambda x: [x["c"].alias("r"), (-x["t"]).alias("h")])
    return df.withColumn("p1", by_count).withColumn("p2", by_log).withColumn("p3", reverse).filter(F.size("p1") > 0).select("node", "n", "p1", "p2", "p3")


def short_pairs(lists: DataFrame, sizes: DataFrame, prefixes: DataFrame, num: int, den: int) -> DataFrame:
    """a, b: pairs of lists of up to SHORT nodes that meet under all orders."""
    short = lists.join(sizes.filter(F.col("len") <= SHORT), "t").select("t", "node", "n")
    mates = short.groupBy("t").agg(F.sort_array(F.collect_list(F.struct("node", "n"))).alias("all"))  # SHORT at most
    one = mates.select("all", F.explode("all").alias("x"))
    pairs = one.select(F.col("x.node").alias("a"), F.explode(F.filter("all", lambda y: (y["node"] > F.col("x.node")) & (F.least(y["n"], F.col("x.n")).cast("long") * den >= F.greatest(y["n"], F.col("x.n")).cast("long") * num))).alias("y"))
    pairs = pairs.select("a", F.col("y.node").alias("b")).distinct()
    others = prefixes.select("node", "p2", "p3")
    for side in "ab":
        pairs = pairs.join(others.select(F.col("node").alias(side), F.col("p2").alias(f"{side}2"), F.col("p3").alias(f"{side}3")), side)
    return pairs.filter(F.arrays_overlap("a2", "b2") & F.arrays_overlap("a3", "b3")).select("a", "b")


def grouped(rows: DataFrame, groups: DataFrame | None, node: str, out: str) -> DataFrame:
    """Adds ``out``: the group of ``node`` so far, or the node itself."""
    if groups is None:
        return rows.withColumn(out, F.col(node))
    return rows.join(groups.select(F.col("node").alias(node), F.col("root").alias("_root")), node, "left").withColumn(out, F.coalesce("_root", node)).drop("_root")


def unfinished(entries: DataFrame, seed: int) -> DataFrame:
    """t, comp, pick: for each list of nodes (t, node, comp) in two groups or more, its largest group and a node of that."""
    h = F.xxhash64("node", F.lit(seed))
    by = entries.groupBy("t", "comp").agg(F.count("*").alias("n"), F.max(F.struct(h.alias("h"), "node")).alias("top"))
    best = by.groupBy("t").agg(F.count("*").alias("groups"), F.max(F.struct("n", "top", "comp")).alias("best")).filter("groups > 1")
    return best.select("t", F.col("best.comp").alias("main"), F.col("best.top.node").alias("pick"))


def star_cells(scratch: Scratch, stars: DataFrame) -> DataFrame:
    """``stars``: a, b. cell, side, node: a with up to PARTNERS of its partners each time."""
    counts = stars.groupBy("a").agg(F.ceil(F.count("*") / min(CELL, PARTNERS)).cast("int").alias("k"))
    cut = stars.join(scratch.stash(counts), "a").withColumn("i", F.pmod(F.xxhash64("b"), F.col("k")).cast("int"))
    cell = F.xxhash64("a", "i", F.lit("star"))
    heads = cut.select(cell.alias("cell"), F.lit(0).alias("side"), F.col("a").alias("node")).distinct()
    return heads.union(cut.select(cell, F.lit(1), F.col("b")))


def block_cells(scratch: Scratch, members: DataFrame, num: int, den: int) -> DataFrame:
    """``members``: node, n, block, comp, rest (outside the block's largest group). Gives each node its cells: cell, side, node, comp.

    A band holds sizes within one factor den/num, so links stay within a band or between neighbours. Sets of a block, a band
    and one side of ``rest`` are a class, cut into chunks; all classes that could link meet, but for the largest group itself.
    """
    band = F.floor(F.log(F.col("n").cast("double")) / float(np.log(den / num) * 1.001)).cast("int")
    members = members.withColumn("band", band).withColumn("of", F.struct("band", "rest"))
    k = F.ceil(F.greatest(F.count("*") / CELL, F.sum("n") / CELL_TOKENS)).cast("int")
    sides = scratch.stash(members.groupBy("block", "of").agg(k.alias("k")))
    lo, hi = (sides.select("block", F.col("of").alias(f"{x}_of"), F.col("k").alias(f"{x}_k")) for x in ("lo", "hi"))
    near = (F.col("lo_of") <= F.col("hi_of")) & (F.col("hi_of.band") - F.col("lo_of.band") <= 1) & (F.col("lo_of.rest") | F.col("hi_of.rest"))
    meet = scratch.stash(lo.join(hi, "block").filter(near))  # a row for each two neighbouring classes of a block
    m = members.join(sides, ["block", "of"]).withColumn("i", F.pmod(F.xxhash64("node"), F.col("k")).cast("int")).drop("k")
    first = m.join(meet.withColumnRenamed("lo_of", "of"), ["block", "of"])
    own, j = F.col("of") == F.col("hi_of"), F.explode(F.sequence(F.lit(0), F.col("hi_k") - 1)).alias("j")
    first = first.select("*", j).withColumn("x", F.when(own, F.least("i", "j")).otherwise(F.col("i"))).withColumn("y", F.when(own, F.greatest("i", "j")).otherwise(F.col("j")))
    side = F.when(~own, 0).when(F.col("x") == F.col("y"), 2).when(F.col("i") == F.col("x"), 0).otherwise(1)
    first = first.select(F.xxhash64("block", "of.band", "of.rest", "x", "hi_of.band", "hi_of.rest", "y").alias("cell"), side.alias("side"), "node", "comp")
    second = m.join(meet.filter("lo_of != hi_of").withColumnRenamed("hi_of", "of"), ["block", "of"]).select("*", F.explode(F.sequence(F.lit(0), F.col("lo_k") - 1)).alias("x"))
    second = second.select(F.xxhash64("block", "lo_of.band", "lo_of.rest", "x", "of.band", "of.rest", "i"), F.lit(1), "node", "comp")
    return first.union(second)


def links_of(scratch: Scratch, slim: DataFrame, names: DataFrame, prefixes: DataFrame, k: int, num: int, den: int, most: int) -> DataFrame:
    """a, b, checked: edges that join all nodes of a group (a null edge carries the pairs that a cell verified)."""
    lists = prefixes.select("node", "n", F.explode("p1").alias("t"))
    sizes = scratch.stash(lists.groupBy("t").agg(F.count("*").alias("len")).filter("len > 1"))
    pairs = scratch.stash(short_pairs(lists, sizes, prefixes, num, den))
    long = scratch.stash(lists.join(sizes.filter(F.col("len") > SHORT), "t").select("t", "node"))
    suspects = pairs.select(F.col("a").alias("node")).union(pairs.select("b")).union(long.select("node")).distinct()
    members = scratch.stash(suspects.join(names, "node").join(prefixes.select("node", "p1", "p2", "p3"), "node"))
    scratch.tidy()
    sets = scratch.stash(suspect_sets(slim, members, k, most))  # prefixes come with the members: sets move once
    scratch.drop(members)

    def verified(cells: DataFrame) -> DataFrame:
        found = scratch.stash(cells.join(sets, "node").groupBy("cell").applyInArrow(lambda t: compare(t, num, den), LINKS))
        scratch.tidy()
        return found

    links, groups = [], None

    def united() -> DataFrame:
        every = links[0]
        for x in links[1:]:
            every = every.union(x)
        return every

    for turn in range(ROUNDS):
        entries = scratch.stash(grouped(long, groups, "node", "comp"))
        left = unfinished(entries, turn)
        stars = entries.join(left, "t").filter("comp != main and node != pick").select(F.col("pick").alias("a"), F.col("node").alias("b")).distinct()
        stars = scratch.stash(stars)
        asked = stars.count()
        if not asked:
            break
        links.append(verified(star_cells(scratch, stars).withColumn("comp", F.col("node"))))
        groups = components(scratch, united().filter("a is not null").select("a", "b"))
        if links[-1].filter("a is not null").count() * 4 < asked:
            break
    entries = grouped(long, groups, "node", "comp")
    open_ = scratch.stash(entries.join(unfinished(entries, 0).select("t", "main"), "t"))
    pairs = grouped(grouped(pairs, groups, "a", "ca"), groups, "b", "cb").filter("ca != cb")
    pairs = scratch.stash(pairs)
    blocks = components(scratch, pairs.select(F.col("ca").alias("a"), F.col("cb").alias("b")).union(open_.filter("comp != main").select("main", "comp")).distinct())
    inside = pairs.select(F.col("a").alias("node"), F.col("ca").alias("comp")).union(pairs.select("b", "cb")).union(open_.select("node", "comp")).distinct()
    inside = inside.join(blocks.select(F.col("node").alias("comp"), F.col("root").alias("block")), "comp").join(names.select("node", "n"), "node")
    inside = scratch.stash(inside)
    main = inside.groupBy("block", "comp").agg(F.count("*").alias("c")).groupBy("block").agg(F.max(F.struct("c", "comp")).getField("comp").alias("main"))
    inside = inside.join(main, "block").select("node", "n", "block", "comp", (F.col("comp") != F.col("main")).alias("rest"))
    links.append(verified(block_cells(scratch, inside, num, den)))
    return united()


def own_numbers(scratch: Scratch, found: DataFrame) -> DataFrame:
    """``found`` with ``sig`` made unique: of sets that share a first half, all but one are numbered by both halves."""
    clash = found.groupBy("sig").agg(F.min("sig2").alias("keeps"), F.max("sig2").alias("other")).filter("keeps != other")
    clash = scratch.stash(clash.select("sig", "keeps"))
    if not clash.head(1):
        return found.withColumn("node", F.col("sig"))
    return found.join(clash, "sig", "left").withColumn("node", F.when(F.col("sig2") != F.col("keeps"), F.xxhash64("sig", "sig2")).otherwise(F.col("sig"))).drop("keeps")


def spread_join(rows: DataFrame, ids: DataFrame, key: str, salts: int) -> DataFrame:
    """Left join of ``rows`` (key, row) with ``ids`` (one row for each key) in which a key of very many rows is dealt to many
    tasks: the key's row goes to each of its salts first, and rows look there."""
    rows = rows.withColumn("salt", F.pmod(F.xxhash64("row", "doc_id"), F.lit(salts)).cast("int"))
    places = rows.filter(F.col(key).isNotNull()).groupBy(key, "salt").agg(F.count("*").alias("_n")).drop("_n")
    return rows.join(places.join(ids, key), [key, "salt"], "left").drop("salt")


def similar_groups(docs: DataFrame, k: int = 5, num: int = 80, den: int = 100, most: int = screen.MOST, group: bool = False) -> DataFrame:
    """doc_id, n_shingles, component_id, sig, row and row2 (two halves of a key of doc_id and text) for every row of ``docs``.

    With ``group`` also a key of the group, which is not null where ids are; null for texts without words. Two documents link when ``den * common >= num * union`` of their k-word shingle sets.
    """
    scratch = Scratch(docs.sparkSession)
    region = min(0.499, 4 / 3 * (1 - num / den))
    slim = only(docs, "doc_id", "text").select("doc_id", F.xxhash64("doc_id", "text").alias("row"), F.xxhash64("text", "doc_id").alias("row2"), "text")
    found = scratch.stash(slim.mapInArrow(lambda it: tokenise(it, k, num, den, region), SETS))
    found, stored = own_numbers(scratch, found), found
    nodes = found.filter("node is not null").groupBy("node").agg(F.min("doc_id").alias("low"), F.min("row").alias("row"), F.first("n").alias("n"), F.min("sig").alias("sig"), F.min("sig2").alias("sig2"), F.first("entries").alias("entries"))
    nodes = scratch.stash(nodes)
    rows = scratch.stash(found.select("doc_id", "row", "row2", "n", "node"))
    scratch.drop(stored)

    entries = nodes.select("node", F.explode("entries").alias("t"))
    df = scratch.stash(entries.groupBy("t").agg(F.count("*").alias("c")).filter("c > 1"))
    scratch.tidy()  # the exchange that counted them, before the next one
    shared = entries.join(df, "t").groupBy("node").agg(F.collect_list(F.struct("c", "t")).alias("common"))  # part of one text's shingles
    prefixes = scratch.stash(prefix_arrays(shared.join(nodes.select("node", "n", F.size("entries").alias("held")), "node"), num, den))
    names = scratch.stash(nodes.drop("entries"))
    scratch.drop(nodes, df)

    links = links_of(scratch, slim, names, prefixes, k, num, den, most)
    groups = components(scratch, links.filter("a is not null").select("a", "b"))
    named = groups.join(names.select("node", "low"), "node")
    low = named.groupBy("root").agg(F.min("low").alias("group_low"))
    named = named.join(low, "root").select("node", "group_low", F.col("root").alias("group"))
    ids = names.select("node", "low").join(named, "node", "left").select("node", F.coalesce("group_low", "low").alias("component"), F.coalesce("group", "node").alias("group"))
    out = spread_join(rows, scratch.stash(ids), "node", bucket_count(rows.count()))
    more = ["group"] if group else []
    out = out.select("doc_id", F.col("n").cast("long").alias("n_shingles"), F.when(F.col("node").isNull(), F.col("doc_id")).otherwise(F.col("component")).alias("component_id"), F.col("node").alias("sig"), "row", "row2", *more)
    out = scratch.stash(out)
    scratch.drop(rows, names, prefixes)
    return out
