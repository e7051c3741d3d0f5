"""Contigs of the documents' repeated k-mers."""

from __future__ import annotations

from distds.plans import contigs as c
from distds.plans import stretches as st
from distds.queries.kmers import K, MERS
from distds.sources.io import forget, settle, table


def dealt(spark, d):
    """Stretches of the documents, and the number of parts they are dealt to."""
    docs = table(spark, d, "documents")
    parts = st.part_count(docs, "text")
    return st.deal(docs, "text", K, parts, True), parts


def steps(spark, d):
    stretches, parts = dealt(spark, d)
    s = settle(st.steps(stretches, K, parts))
    del stretches
    forget(spark)
    return s


def fragments(spark, d):
    return c.fragments(table(spark, d, "documents"), "text", K)


def cg_nodes(spark, d):
    return st.nodes(dealt(spark, d)[0], K)


def cg_nodes_strict(spark, d):
    return st.nodes(dealt(spark, d)[0], K, strict=True)


def cg_edges(spark, d):
    return st.edges(steps(spark, d), K)


def cg_heads(spark, d):
    return st.heads(steps(spark, d), K)


def cg_walk(spark, d):
    f = fragments(spark, d)
    return c.walked(f, c.fragment_edges(f), K)


def cg_double(spark, d):
    """Steps across parts are inserted through the buffered writer, looked up find-only, and chains doubled."""
    f = fragments(spark, d)
    return c.contigs_fragments(f, c.table_edges(f, True), K)


def cg_without_rings(spark, d):
    f = fragments(spark, d)
    return c.contigs_fragments(f, c.fragment_edges(f), K, "drop")


def cg_contracted(spark, d):
    """Chains are shortened inside parts; doubling starts from what crosses them."""
    f = fragments(spark, d)
    return c.contigs_fragments(f, c.fragment_edges(f), K)


def cg_all_seeds(spark, d):
    f = fragments(spark, d)
    return c.walked(f, c.fragment_edges(f), K, seeds=True)


def cg_generic(spark, d):
    """Unbuffered inserts and finds under the strongest promise; chains are walked by the one task that gets them."""
    f = fragments(spark, d)
    return c.walked(f, c.table_edges(f, False), K)


def cg_specialised(spark, d):
    """Two bits a letter in a long, edges by arithmetic on them, no table."""
    f = fragments(spark, d)
    return c.contigs_fragments(f, c.fragment_edges(f), K)


def cg_stats(spark, d):
    return c.stats(cg_specialised(spark, d))


QUERIES = {f.__name__: f for f in (cg_nodes, cg_nodes_strict, cg_edges, cg_heads, cg_walk, cg_double, cg_without_rings, cg_contracted, cg_all_seeds, cg_generic, cg_specialised, cg_stats)}
NODES = f"""{MERS}, g AS (SELECT kmer, count(*) AS n, min(l) AS l0, max(l) AS l1, min(r) AS r0, max(r) AS r1, bool_or(l IS NULL) AS le, bool_or(r IS NULL) AS re FROM mers GROUP BY 1 HAVING count(*) >= 2),
    nodes AS MATERIALIZED (SELECT kmer, CASE WHEN l0 = l1 THEN l0 END AS "left", CASE WHEN r0 = r1 THEN r0 END AS "right", n FROM g)"""
EDGES = f"""{NODES}, edges AS MATERIALIZED (SELECT a.kmer AS src, b.kmer AS dst FROM nodes a JOIN nodes b ON b.kmer = substr(a.kmer, 2) || a."right" AND b."left" = substr(a.kmer, 1, 1)),
    heads AS (SELECT kmer FROM nodes ANTI JOIN edges ON dst = kmer)"""
#: Chains from heads; what they leave are rings, each walked once from its smallest node.
CONTIGS = f"""{EDGES}, walk AS (SELECT kmer AS head, kmer AS node, 0 AS dist FROM heads UNION ALL SELECT head, dst, dist + 1 FROM walk JOIN edges ON src = node),
    rest AS MATERIALIZED (SELECT src, dst FROM edges ANTI JOIN walk ON node = src),
    reach AS (SELECT src AS a, dst AS b FROM rest UNION SELECT a, dst FROM reach JOIN rest ON src = b),
    lows AS MATERIALIZED (SELECT a AS node, min(b) AS low FROM reach GROUP BY 1),
    ring AS (SELECT low AS head, low AS node, 0 AS dist FROM (SELECT DISTINCT low FROM lows) UNION ALL SELECT head, dst, dist + 1 FROM ring JOIN rest ON src = node WHERE dst <> head),
    chains AS (SELECT * FROM walk UNION ALL SELECT * FROM ring),
    built AS (SELECT head, head || coalesce(string_agg(CASE WHEN dist > 0 THEN substr(node, {K}, 1) END, '' ORDER BY dist), '') AS contig, count(*) AS copies FROM chains GROUP BY 1)"""
ALL = f"WITH RECURSIVE {CONTIGS} SELECT head, contig FROM built"
ORACLES = {
    "cg_nodes": f'WITH {NODES} SELECT kmer, "left", "right", n FROM nodes',
    "cg_nodes_strict": f'WITH {NODES} SELECT kmer, l0 AS "left", r0 AS "right", n FROM g WHERE ((l0 = l1 AND NOT le) OR l0 IS NULL) AND ((r0 = r1 AND NOT re) OR r0 IS NULL)',
    "cg_edges": f"WITH {EDGES} SELECT src, dst FROM edges", "cg_heads": f"WITH {EDGES} SELECT kmer FROM heads",
    "cg_walk": ALL, "cg_double": ALL, "cg_contracted": ALL, "cg_generic": ALL, "cg_specialised": ALL,
    "cg_without_rings": f"WITH RECURSIVE {CONTIGS} SELECT head, contig FROM built SEMI JOIN heads ON kmer = head",
    "cg_all_seeds": f"WITH RECURSIVE {CONTIGS} SELECT contig, sum(copies)::BIGINT AS copies FROM built GROUP BY 1",
    "cg_stats": f"""WITH RECURSIVE {CONTIGS}, s AS (SELECT length(contig) AS len, sum(length(contig)) OVER (ORDER BY length(contig) DESC) AS upto, sum(length(contig)) OVER () AS total FROM built)
        SELECT count(*) AS contigs, max(total)::BIGINT AS letters, max(len)::BIGINT AS longest, max(CASE WHEN upto * 2 >= total THEN len END)::BIGINT AS n50 FROM s""",
}
