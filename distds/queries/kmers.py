"""k-mer counting on the documents, read as four letters."""

from __future__ import annotations

from pyspark.sql import functions as F

from distds.functions.codecs import unpack_kmer
from distds.functions.hashing import h60_sql
from distds.operators.relational import strip_tags
from distds.plans import kmers as k
from distds.plans import ordered
from distds.plans import stretches as st
from distds.queries.bloom import mask_sql
from distds.sources.io import table

K = 21


def reads(spark, d):
    return k.reads_from_text(table(spark, d, "documents"), "doc_id", "text")


def mers(spark, d):
    return k.extract(reads(spark, d), K, edges=False)


def counts(spark, d):
    return k.count_plain(mers(spark, d))


def shown(c):
    """Counts of a table of k-mers by their first six letters."""
    return c.groupBy(F.substring("kmer", 1, 6).alias("prefix")).agg(F.count("*").alias("kmers"), F.sum("n").cast("long").alias("total"), F.max("n").cast("long").alias("most"))


def shown_packed(c):
    """The same for packed k-mers."""
    g = c.groupBy(F.shiftright("kmer", 2 * (K - 6)).alias("prefix")).agg(F.count("*").alias("kmers"), F.sum("n").cast("long").alias("total"), F.max("n").cast("long").alias("most"))
    return g.withColumn("prefix", unpack_kmer(F.col("prefix"), 6))


def dealt(spark, d):
    docs = table(spark, d, "documents")
    return st.deal(docs, "text", K, st.part_count(docs, "text"), True)


def km_extract(spark, d):
    x = k.extract(reads(spark, d), K)
    return x.groupBy("read_id").agg(F.count("*").alias("n"), F.sum("p").cast("long").alias("places"), F.count("left").alias("lefts"), F.count("right").alias("rights"), F.min("kmer").alias("low"), F.max("kmer").alias("high"))


def km_invalid(spark, d):
    """Reads that keep invalid letters as N: k-mers with and without one."""
    r = k.reads_from_text(table(spark, d, "documents"), "doc_id", "text", invalid=True)
    x = k.extract(r, K, edges=False)
    return x.groupBy("read_id").agg(F.count("*").alias("n"), F.sum(F.when(F.col("kmer").contains("N"), 0).otherwise(1)).cast("long").alias("valid"))


def km_count(spark, d):
    return shown(counts(spark, d))


def km_spectrum(spark, d):
    return k.spectrum(counts(spark, d))


def km_repeat(spark, d):
    return shown(counts(spark, d).filter("n > 1"))


def km_bloom(spark, d):
    """One filter over all k-mers, sized by the number of sightings and run in rounds over its blocks."""
    return ordered.report(table(spark, d, "documents"), "doc_id", "text", K, 4)


def km_bloom_exact(spark, d):
    """A filter of first sightings in each part, with false positives taken off: true counts of repeated k-mers."""
    return shown_packed(st.count_absorbed(dealt(spark, d), K))


def km_two_level(spark, d):
    return shown_packed(st.count_filtered(dealt(spark, d), K))


def km_localised(spark, d):
    r = reads(spark, d)
    parts = max(8, -(-k.sightings(r, K) // 4_000_000))  # sightings that an owner holds
    return shown(k.count_localised(k.extract(r, K, edges=False), parts, K))


def km_filter_report(spark, d):
    return st.filter_report(dealt(spark, d), K)


def km_words(spark, d):
    c = k.count_plain(k.shingles(table(spark, d, "documents"), "doc_id", "text", 5))
    return k.spectrum(c)


def km_pages(spark, d):
    """Word 3-grams of page texts, tags removed."""
    p = table(spark, d, "pages").select("page_id", strip_tags(F.col("html")).alias("t"))
    return k.spectrum(k.count_plain(k.shingles(p, "page_id", "t", 3)))


def km_turns(spark, d):
    """Word 3-grams by turn of a conversation."""
    c = table(spark, d, "conversations").select(F.struct("conv_id", "turn").alias("id"), "text")
    return k.spectrum(k.count_plain(k.shingles(c, "id", "text", 3)))


def km_memory(spark, d):
    return k.memory_report(counts(spark, d), K)


def km_canonical(spark, d):
    c = mers(spark, d).select(k.canonical(F.col("kmer")).alias("kmer")).groupBy("kmer").agg(F.count("*").alias("n"))
    return k.spectrum(c)


QUERIES = {f.__name__: f for f in (km_extract, km_invalid, km_count, km_spectrum, km_repeat, km_bloom, km_bloom_exact, km_two_level, km_localised, km_filter_report, km_words, km_pages, km_turns, km_memory, km_canonical)}
LOW = f"translate(text, '{k.LETTERS.upper()}', '{k.LETTERS}')"
READS = f"reads AS (SELECT doc_id AS read_id, translate(regexp_replace({LOW}, '[^a-z]', '', 'g'), '{k.LETTERS}', '{k.BASES}') AS seq FROM documents)"
PLACES = f"spots AS (SELECT read_id, seq, unnest(range(1, length(seq) - {K - 2}))::INT AS p FROM reads WHERE length(seq) >= {K})"
MERS = f"{READS}, {PLACES}, mers AS (SELECT read_id, p, substr(seq, p, {K}) AS kmer, CASE WHEN p > 1 THEN substr(seq, p - 1, 1) END AS l, CASE WHEN p + {K} <= length(seq) THEN substr(seq, p + {K}, 1) END AS r FROM spots)"
COUNTS = f"{MERS}, c AS (SELECT kmer, count(*) AS n FROM mers GROUP BY 1)"
SHOWN = "SELECT substr(kmer, 1, 6) AS prefix, count(*) AS kmers, sum(n)::BIGINT AS total, max(n) AS most FROM c"
GRAMS = "WITH w AS (SELECT string_split({t}, ' ') AS w FROM {f}), g AS (SELECT w, unnest(range(1, len(w) - 1))::INT AS i FROM w WHERE len(w) >= 3), c AS (SELECT array_to_string(w[i:i + 2], ' ') AS kmer, count(*) AS n FROM g GROUP BY 1) SELECT n, count(*) AS kmers FROM c GROUP BY 1"
ORACLES = {
    "km_extract": f"WITH {MERS} SELECT read_id, count(*) AS n, sum(p)::BIGINT AS places, count(l) AS lefts, count(r) AS rights, min(kmer) AS low, max(kmer) AS high FROM mers GROUP BY 1",
    "km_invalid": f"WITH reads AS (SELECT doc_id AS read_id, translate(regexp_replace({LOW}, '[^a-z]', '#', 'g'), '{k.LETTERS}#', '{k.BASES}N') AS seq FROM documents), {PLACES} SELECT read_id, count(*) AS n, sum(CASE WHEN contains(substr(seq, p, {K}), 'N') THEN 0 ELSE 1 END)::BIGINT AS valid FROM spots GROUP BY 1",
    "km_count": f"WITH {COUNTS} {SHOWN} GROUP BY 1", "km_repeat": f"WITH {COUNTS} {SHOWN} WHERE n > 1 GROUP BY 1", **{q: f"WITH {COUNTS} {SHOWN} WHERE n > 1 GROUP BY 1" for q in ("km_two_level", "km_localised", "km_bloom_exact")},
    "km_spectrum": f"WITH {COUNTS} SELECT n, count(*) AS kmers FROM c GROUP BY 1",
    "km_bloom": f"""WITH {MERS}, size AS (SELECT (1::BIGINT << ceil(log2(ceil(count(*) / {k.LOAD}.0)))::INT) AS blocks FROM mers), o AS (SELECT kmer, min({{'r': read_id, 'p': p}}) AS seq, count(*) AS occ FROM mers GROUP BY 1),
        m AS (SELECT kmer, seq, occ, {h60_sql('kmer', 1)} % (SELECT blocks FROM size) AS block, {mask_sql('kmer')} AS mask FROM o),
        f AS (SELECT kmer, occ, ((coalesce(bit_or(mask) OVER (PARTITION BY block ORDER BY seq ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0::UBIGINT) & mask) = mask)::BIGINT AS fp FROM m)
        SELECT substr(kmer, 1, 4) AS prefix, count(*) AS kmers, sum(fp)::BIGINT AS fp, sum(occ - 1 + fp)::BIGINT AS hits, sum(occ + fp)::BIGINT AS reported, sum(occ)::BIGINT AS occ FROM f WHERE occ - 1 + fp >= 1 GROUP BY 1""",
    "km_pages": GRAMS.format(t="regexp_replace(html, '<[^>]*>', '', 'g')", f="pages"), "km_turns": GRAMS.format(t="text", f="conversations"),
    "km_words": """WITH w AS (SELECT doc_id, string_split(text, ' ') AS w FROM documents), g AS (SELECT w, unnest(range(1, len(w) - 3))::INT AS i FROM w WHERE len(w) >= 5),
        c AS (SELECT array_to_string(w[i:i + 4], ' ') AS kmer, count(*) AS n FROM g GROUP BY 1) SELECT n, count(*) AS kmers FROM c GROUP BY 1""",
    "km_memory": f"WITH {COUNTS} SELECT count(*) AS all_entries, sum((n > 1)::BIGINT)::BIGINT AS kept_entries, count(*) * {K + 8} AS plain_bytes, (sum((n > 1)::BIGINT) * {K + 8} + count(*) * 16 // 8)::BIGINT AS filtered_bytes FROM c",
    "km_canonical": f"WITH {MERS}, c AS (SELECT least(kmer, translate(reverse(kmer), 'ACGT', 'TGCA')) AS m, count(*) AS n FROM mers GROUP BY 1) SELECT n, count(*) AS kmers FROM c GROUP BY 1",
}
