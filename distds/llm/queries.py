"""The queries of this subpackage: each applies one operator to its whole intended table."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from distds.llm import quality
from distds.llm.exactdedup import exact_dedup
from distds.llm.jaccard import similar_groups
from distds.llm.licenses import scan_licenses
from distds.llm.linededup import dedup_lines, host_of, page_text
from distds.llm.mih import nearest
from distds.llm.mixing import mix
from distds.llm.packing import best_fit
from distds.llm.scratch import LOWER, UPPER, Scratch
from distds.llm.secrets import KINDS, LEAST, PATTERNS, scan_secrets
from distds.llm.sharding import shard_documents


def read(spark: SparkSession, sf_dir: str, table: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{table}.parquet")


def quality_weights(spark: SparkSession, sf_dir: str) -> DataFrame:
    """doc_id, q: 2 for documents labelled good, 0.5 for those labelled bad."""
    labels = read(spark, sf_dir, "labels").filter("doc_id is not null").groupBy("doc_id").agg(F.max("quality").alias("quality"))
    return labels.select("doc_id", F.when(F.col("quality") == 1, 2.0).when(F.col("quality") == 0, 0.5).otherwise(1.0).alias("q"))


def op1_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = read(spark, sf_dir, "documents")
    return mix(docs, quality=quality_weights(spark, sf_dir)).select("doc_id", "size", "source_size", "target", "taken", "copies")


def op2_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    pages = read(spark, sf_dir, "pages").select("page_id", "url", page_text(F.col("html")).alias("text"))
    pages = Scratch(spark).stash(pages)  # pages are parsed once
    return dedup_lines(pages, host_of(F.col("url")), count=True).drop("url")


def op3_exact_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Documents count as four batches by id: three snapshots and the incoming one, each screened by those before."""
    return exact_dedup(read(spark, sf_dir, "documents"), F.pmod(F.coalesce("doc_id", F.lit(0)), F.lit(4)))


def op4_secret_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    return scan_secrets(read(spark, sf_dir, "documents"), Scratch(spark))


def op5_jaccard_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    return similar_groups(read(spark, sf_dir, "documents"), k=4, num=85, den=100).select("doc_id", "n_shingles", "component_id")


def op6_best_fit_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return best_fit(read(spark, sf_dir, "documents"))


def op7_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = read(spark, sf_dir, "documents")
    fold = F.pmod(F.crc32(F.coalesce(F.col("doc_id").cast("string"), F.lit(""))), F.lit(5))
    labels = read(spark, sf_dir, "labels").filter(fold != 0).select("doc_id", F.col("quality").alias("y"))
    scored = quality.score(docs.select("doc_id", "text"), quality.fit(docs, labels))
    return scored.select("doc_id", (fold == 0).alias("held_out"), "score", (F.col("score") >= 0.3).cast("int").alias("predicted"))


def op8_license_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    return scan_licenses(read(spark, sf_dir, "documents"))


def op9_nearest(spark: SparkSession, sf_dir: str) -> DataFrame:
    return nearest(read(spark, sf_dir, "embeddings"), F.col("vec_id") % 20 == 0)


def op10_sharding(spark: SparkSession, sf_dir: str) -> DataFrame:
    return shard_documents(read(spark, sf_dir, "documents")).drop("hub")


def queries() -> dict:
    return {k: v for k, v in globals().items() if k.startswith("op") and k[2].isdigit()}


WORDS = r"[^\x20\x09-\x0D]+"
FOLD = f"translate(coalesce(text, ''), '{UPPER}', '{LOWER}')"
OP1 = rf"""WITH d AS (SELECT doc_id, source, len(regexp_extract_all(coalesce(text, ''), '{WORDS}'))::BIGINT AS size FROM documents),
    lab AS (SELECT doc_id, CASE max(quality) WHEN 1 THEN 2.0::DOUBLE WHEN 0 THEN 0.5::DOUBLE ELSE 1.0::DOUBLE END AS q FROM labels WHERE doc_id IS NOT NULL GROUP BY 1),
    k AS (SELECT d.*, -ln((('0x' || substr(md5(coalesce(doc_id::VARCHAR, '') || '#' || size), 1, 13))::BIGINT::DOUBLE + 0.5::DOUBLE) / 4503599627370496::DOUBLE) / coalesce(q, 1.0::DOUBLE) AS key FROM d LEFT JOIN lab USING (doc_id)),
    s AS (SELECT source, sum(size)::BIGINT AS source_size, row_number() OVER (ORDER BY source NULLS LAST) - 1 AS pos FROM d GROUP BY source),
    w AS (SELECT *, [5, 2, 1][pos % 3 + 1]::DOUBLE AS weight, 2.0::DOUBLE * source_size AS cap, sum(source_size) OVER ()::DOUBLE AS total FROM s),
    r AS (SELECT *, cap / weight AS ratio, coalesce(sum(cap) OVER p, 0) AS c_before, sum(weight) OVER () - coalesce(sum(weight) OVER p, 0) AS w_left FROM w WINDOW p AS (ORDER BY cap / weight, source ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING)),
    lam AS (SELECT arg_min((1.5::DOUBLE * total - c_before) / w_left, ratio) AS lam FROM r WHERE (1.5::DOUBLE * total - c_before) / w_left <= ratio),
    t AS (SELECT source, source_size, least(cap, lam * weight) AS target FROM w CROSS JOIN lam),
    e AS (SELECT *, CASE WHEN source_size > 0 THEN floor(target / source_size)::BIGINT ELSE 0 END AS epochs FROM t),
    o AS (SELECT k.*, source_size, target, epochs, coalesce(sum(size) OVER (PARTITION BY k.source ORDER BY key, doc_id, size ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) + size / 2.0::DOUBLE <= target - epochs * source_size AND source_size > 0 AS chosen FROM k JOIN e ON k.source IS NOT DISTINCT FROM e.source)
    SELECT doc_id, size, source_size, target, (size * (epochs + chosen::BIGINT))::BIGINT AS taken, (epochs + chosen::BIGINT)::INT AS copies FROM o"""
OP2 = r"""WITH a AS (SELECT page_id, lower(regexp_extract(url, '^[A-Za-z][A-Za-z0-9+.-]*://([^/?#]*)', 1)) AS h, regexp_replace(regexp_replace(regexp_replace(html,
        '(?is)<(?:script\b.*?</script>|style\b.*?</style>|!--.*?-->)', '', 'g'), '(?i)</?(?:br|p|div|li|h[1-6]|tr|title|article|nav|ul|ol|table)\b[^>]*>', chr(10), 'g'), '<[^>]*>', '', 'g') AS t FROM pages),
    b AS (SELECT page_id, h, list_filter(list_transform(string_split(replace(replace(replace(replace(t, '&lt;', '<'), '&gt;', '>'), '&quot;', '"'), '&amp;', '&'), chr(10)), lambda x: trim(x)), lambda x: x <> '') AS l FROM a),
    total AS (SELECT h, count(*) AS pages FROM b GROUP BY 1),
    freq AS (SELECT h, line, count(*) AS n FROM (SELECT page_id, h, unnest(list_distinct(l)) AS line FROM b) GROUP BY 1, 2),
    boiler AS (SELECT h, list(line) AS lines FROM freq JOIN total USING (h) WHERE n - 1 > (pages - 1) * 0.1::DOUBLE GROUP BY 1),
    k AS (SELECT page_id, l, list_filter(l, lambda x: NOT coalesce(list_contains(lines, x), false)) AS kept FROM b LEFT JOIN boiler USING (h))
    SELECT page_id, array_to_string(kept, chr(10)) AS text, greatest(len(l), 1)::BIGINT AS n_lines, (len(l) - len(kept))::BIGINT AS n_dropped FROM k"""
OP3 = f"""WITH d AS (SELECT doc_id, {FOLD} AS t, coalesce(doc_id, 0) % 4 AS gen FROM documents)
    SELECT doc_id, max(doc_id) OVER w AS keep_id, count(*) OVER w AS group_size, doc_id = max(doc_id) OVER w AS kept, sha256(t) AS text_sha256, min(gen) OVER w < gen AS seen_before FROM d WINDOW w AS (PARTITION BY t)"""
OP5 = rf"""WITH RECURSIVE w AS (SELECT doc_id, regexp_extract_all({FOLD}, '{WORDS}') AS w FROM documents),
    g AS (SELECT DISTINCT doc_id, array_to_string(w[i:i + 3], ' ') AS g FROM (SELECT doc_id, w, unnest(range(1, greatest(len(w) - 3, 1) + 1))::INT AS i FROM w WHERE len(w) > 0)),
    n AS (SELECT doc_id, count(*) AS n FROM g GROUP BY 1),
    c AS (SELECT a.doc_id AS a, b.doc_id AS b, count(*) AS c FROM g a JOIN g b ON a.g = b.g AND a.doc_id < b.doc_id GROUP BY ALL),
    link AS MATERIALIZED (SELECT a, b FROM c JOIN n x ON x.doc_id = a JOIN n y ON y.doc_id = b WHERE 100 * c >= 85 * (x.n + y.n - c)),
    pair AS MATERIALIZED (SELECT a, b FROM link UNION ALL SELECT b, a FROM link),
    reach AS (SELECT a, b FROM pair UNION SELECT r.a, p.b FROM reach r JOIN pair p ON p.a = r.b)
    SELECT w.doc_id, coalesce(n, 0) AS n_shingles, least(w.doc_id, coalesce(low, w.doc_id)) AS component_id FROM w LEFT JOIN n USING (doc_id) LEFT JOIN (SELECT a AS doc_id, min(b) AS low FROM reach GROUP BY 1) USING (doc_id)"""


def secrets_sql(scope: int = 300) -> str:
    """Matches are laid out from the pieces between them; parts near each other are found by their gaps."""
    each = []
    for i, (kind, least) in enumerate(LEAST.items()):
        p = PATTERNS[kind].replace("'", "''")
        extra = " AND regexp_matches(v, '[0-9]') AND regexp_matches(v, '[A-Za-z]')" if kind == "key" else ""
        each.append(f"""SELECT doc_id, {i} AS k, s, s + length(m) AS e FROM (SELECT doc_id, m, v, sum(length(g)) OVER (PARTITION BY doc_id ORDER BY i) + coalesce(sum(length(m)) OVER (PARTITION BY doc_id ORDER BY i ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS s
            FROM (SELECT doc_id, unnest(m) AS m, unnest(v) AS v, unnest(g[1:len(m)]) AS g, unnest(range(len(m))) AS i FROM (SELECT doc_id, regexp_extract_all(t, '({p})', 1) AS m, regexp_extract_all(t, '({p})', 2) AS v, string_split_regex(t, '{p}') AS g FROM d WHERE regexp_matches(t, '{p}')))) WHERE length(v) >= {least}{extra}""")
    names = "[" + ", ".join(f"'{k}'" for k in KINDS) + "]"
    text = f"string_agg(list_extract({names}, k + 1) || ':' || s || ':' || e, ',' ORDER BY s, k)"
    return f"""WITH d AS (SELECT doc_id, coalesce(text, '') AS t FROM documents), every AS ({" UNION ALL ".join(each)}),
        clear AS (SELECT * FROM every x WHERE k < 3 OR NOT EXISTS (SELECT 1 FROM every y WHERE y.doc_id = x.doc_id AND y.k < 3 AND y.s < x.e AND x.s < y.e)),
        near AS (SELECT *, EXISTS (SELECT 1 FROM clear y WHERE y.doc_id = x.doc_id AND y.k IN (1, 3) AND y.s <= x.e + {scope} AND y.e >= x.s - {scope}) AS who,
            EXISTS (SELECT 1 FROM clear y WHERE y.doc_id = x.doc_id AND y.k IN (0, 2, 4) AND y.s <= x.e + {scope} AND y.e >= x.s - {scope}) AS what FROM clear x),
        kept AS (SELECT * FROM near WHERE k < 3 OR (k = 3 AND what) OR (k = 4 AND who) OR (k = 5 AND who AND what)),
        sums AS (SELECT doc_id, count(*) FILTER (k = 0) AS n_assign, count(*) FILTER (k = 1) AS n_access, count(*) FILTER (k = 2) AS n_hex, count(*) FILTER (k > 2) AS n_linked, {text} FILTER (k < 3) AS base, {text} AS spans FROM kept GROUP BY 1)
        SELECT d.doc_id, coalesce(n_assign, 0) AS n_assign, coalesce(n_access, 0) AS n_access, coalesce(n_hex, 0) AS n_hex, sha256(coalesce(base, '')) AS base_sha256, coalesce(spans, '') AS spans, coalesce(n_linked, 0) AS n_linked FROM d LEFT JOIN sums USING (doc_id)"""


def oracle_sql() -> dict[str, str]:
    """Packing, the classifier, the license scan, nearest neighbours and sharding are tested against brute force instead."""
    return {"op1_mixing": OP1, "op2_line_dedup": OP2, "op3_exact_dedup": OP3, "op4_secret_scan": secrets_sql(), "op5_jaccard_join": OP5}
