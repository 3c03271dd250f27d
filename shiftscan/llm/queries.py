"""The ten operators as registered queries, each over its whole table."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import decontam, katz, langid, licenses, minhash, mixing, secrets, surrogates, urls, vectors


def _table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def _remainder(n: int):
    """crc32 of the doc_id written as text, modulo n."""
    return F.crc32(F.col("doc_id").cast("string").cast("binary")) % n


def op1_license_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    got = licenses.scan(_table(spark, sf_dir, "documents").select("doc_id", "text"))
    sure = F.filter("licenses", lambda x: x.license.isNotNull())
    return got.select(
        "doc_id",
        F.size("licenses").alias("n_blocks"),
        F.array_join(F.array_sort(F.array_distinct(F.transform(sure, lambda x: x.license))), ",").alias("licenses"),
        F.array_max(F.transform(sure, lambda x: x.reduction)).alias("reduction"),
        F.aggregate(sure, F.lit(0), lambda a, x: a + F.size(x.differences)).alias("n_differences"),
    )


# The URL rules, and labels of hosts whose pages the tables' URL list holds.
URL_RULES = [("com", "/", "allow"), ("example.com", "/en/", "block"), ("www.example.com", "/en/", "allow"), ("net", "/es/", "block"), ("net", "/fr/", "block")]
LISTED_LABELS = ["adult-x", "free-bets", "spam-farm"]


def op2_url_filter(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The tables hold no URL list: it is made of the canonical URLs on hosts with certain labels."""
    pages = _table(spark, sf_dir, "pages").select("page_id", "url")
    at = urls.parts(F.col("url"))
    listed = pages.where(F.arrays_overlap(F.split(at.host, r"\."), F.lit(LISTED_LABELS))).select(urls.canonical(at.host, at.path).alias("url"))
    return urls.judge(pages, listed, URL_RULES).select("page_id", "host", "path", "rule", "verdict")


def op3_benchmark_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = _table(spark, sf_dir, "documents").select("doc_id", "text")
    got = decontam.contamination(docs, _table(spark, sf_dir, "benchmark"))
    return got.select("doc_id", (F.size("items") > 0).alias("contaminated"), "items")


def op4_vector_near_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return vectors.near_vectors(_table(spark, sf_dir, "embeddings"))


def op5_secret_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    spans = F.col("secrets.spans")

    def count(kind: int):
        return F.size(F.filter(spans, lambda s: s.kind == kind)).cast("long")

    return secrets.scan(_table(spark, sf_dir, "documents").select("doc_id", "text")).select(
        "doc_id",
        count(0).alias("n_assign"),
        count(1).alias("n_access"),
        count(2).alias("n_hex"),
        F.sha2(secrets.written(F.filter(spans, lambda s: s.kind < 3)).cast("binary"), 256).alias("base_sha256"),
        secrets.written(spans).alias("spans"),
        count(3).alias("n_random"),
    )


# The tree's weights; siblings that are not named weigh 1.
MIX_WEIGHTS = {("web",): 5, ("books",): 3, ("reference",): 2} | {(d, lang): w for d in ("web", "books", "reference") for lang, w in (("en", 4), ("de", 2), ("fr", 2), ("es", 2))}


def mix_levels():
    """domain, language, source. The tables have no domain: a source's number stands in for it."""
    number = F.regexp_extract(F.coalesce("source", F.lit("")), r"([0-9]+)$", 1)
    domain = F.when(number == "", "reference").otherwise(F.get(F.array(F.lit("web"), F.lit("books"), F.lit("reference")), F.pmod(F.crc32(number.cast("binary")), F.lit(3)).cast("int")))
    return [domain, F.col("lang"), F.col("source")]


def op6_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = _table(spark, sf_dir, "documents").select("doc_id", "text", "lang", "source")
    domain, _, _ = mix_levels()
    got = mixing.mix(docs, mix_levels(), MIX_WEIGHTS, fraction=0.6)
    return got.select("doc_id", domain.alias("domain"), "lang", "source", "n_tokens", "n_copies")


def op7_minhash_near_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return minhash.near_duplicates(_table(spark, sf_dir, "documents"), size=4)


def op8_katz_backoff(spark: SparkSession, sf_dir: str) -> DataFrame:
    train = F.coalesce(_remainder(7) != 2, F.lit(False))
    held_out = F.coalesce(_remainder(7) == 2, F.lit(False))
    return katz.score(_table(spark, sf_dir, "documents").select("doc_id", "text"), train).withColumn("held_out", held_out)


# For the tables, which hold nobody's data; whoever has the key can undo the surrogates.
KEY = b"for the tables only, not for data"


def op9_surrogate_generation(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The texts with surrogates, and the number of collisions that the audit of the whole table found."""
    docs = _table(spark, sf_dir, "documents").select("doc_id", "text")
    clashes = surrogates.collisions(surrogates.found(docs, KEY)).count()
    got = surrogates.pseudonymise(docs, KEY)

    def count(kind: str):
        return F.size(F.filter("kinds", lambda x: x == kind)).alias(f"n_{kind}")

    return got.select("doc_id", "text", *map(count, surrogates.KINDS), F.lit(clashes).cast("long").alias("n_collisions"))


def op10_cross_parsing_language(spark: SparkSession, sf_dir: str) -> DataFrame:
    held_out = F.coalesce(_remainder(4) == 2, F.lit(False))
    docs = _table(spark, sf_dir, "documents").select("doc_id", "text", "lang")
    got = langid.identify(docs, train=F.coalesce(_remainder(4) != 2, F.lit(False)))
    return got.select("doc_id", held_out.alias("held_out"), F.col("language.lang_pred").alias("lang_pred"), F.col("language.score").alias("score"))


def queries() -> dict:
    return {k: f for k, f in globals().items() if k.startswith("op") and k[2].isdigit()}


OP2_SQL = r"""
WITH cut AS (
  SELECT page_id, CASE WHEN strpos(url, '://') > 0 THEN substr(url, strpos(url, '://') + 3) END AS rest FROM pages
), split AS (
  SELECT page_id,
         coalesce(translate(regexp_extract(rest, '^([^/?#]*)', 1), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '') AS host,
         coalesce(regexp_extract(rest, '^[^/?#]*([^?#]*)', 1), '') AS path
  FROM cut
), named AS (
  SELECT *, regexp_replace(host, '^www\.', '') || regexp_replace(regexp_replace(path, '/index\.html?$', '/'), '/+$', '') AS canon FROM split
), listed AS (
  SELECT DISTINCT canon FROM named WHERE list_has_any(string_split(host, '.'), ['adult-x', 'free-bets', 'spam-farm'])
), rules(h, p, verdict) AS (
  VALUES ('com', '/', 'allow'), ('example.com', '/en/', 'block'), ('www.example.com', '/en/', 'allow'), ('net', '/es/', 'block'), ('net', '/fr/', 'block')
), fits AS (
  SELECT page_id, arg_max(h || p, length(h || p)) AS rule, arg_max(verdict, length(h || p)) AS verdict
  FROM named JOIN rules ON (host = h OR ends_with(host, '.' || h)) AND starts_with(path, p)
  GROUP BY page_id
)
SELECT n.page_id, n.host, n.path, f.rule,
       coalesce(f.verdict, CASE WHEN n.canon IN (SELECT canon FROM listed) THEN 'block' ELSE 'allow' END) AS verdict
FROM named n LEFT JOIN fits f ON n.page_id = f.page_id
"""


OP4_SQL = """
WITH RECURSIVE good AS (
  SELECT DISTINCT vec_id, embedding::DOUBLE[] AS v FROM embeddings
  WHERE vec_id IS NOT NULL AND len(embedding) > 0 AND len([x FOR x IN embedding IF x IS NULL OR NOT isfinite(x)]) = 0 AND len([x FOR x IN embedding IF x <> 0]) > 0
), links AS (
  SELECT a.vec_id AS a, b.vec_id AS b FROM good a JOIN good b
    ON len(a.v) = len(b.v) AND a.vec_id <> b.vec_id AND list_cosine_similarity(a.v, b.v) >= 0.95
), reach(a, b) AS (
  SELECT a, b FROM links UNION SELECT r.a, l.b FROM reach r JOIN links l ON r.b = l.a
), counts AS (
  SELECT a, count(*) AS n FROM links GROUP BY a
), lowest AS (
  SELECT a, min(b) AS low FROM reach GROUP BY a
)
SELECT e.vec_id, coalesce(c.n, 0) AS n_links, least(e.vec_id, coalesce(m.low, e.vec_id)) AS component_id,
       e.vec_id = least(e.vec_id, coalesce(m.low, e.vec_id)) AS kept
FROM embeddings e LEFT JOIN counts c ON c.a = e.vec_id LEFT JOIN lowest m ON m.a = e.vec_id
"""

OP7_SQL = r"""
WITH RECURSIVE worded AS (
  SELECT doc_id, regexp_extract_all(translate(text, 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x20\x09-\x0D]+') AS w FROM documents
), sets AS (
  SELECT doc_id, CASE WHEN len(w) >= 4 THEN list_distinct([array_to_string(w[k:k + 3], ' ') FOR k IN range(1, len(w) - 2)])
                      WHEN len(w) > 0 THEN [array_to_string(w, ' ')] ELSE [] END AS s
  FROM worded
), shingles AS (
  SELECT doc_id, len(s) AS n, unnest(s) AS g FROM sets
), shared AS (
  SELECT a.doc_id AS a, b.doc_id AS b, a.n AS n_a, b.n AS n_b, count(*) AS both_
  FROM shingles a JOIN shingles b ON a.g = b.g AND a.doc_id <> b.doc_id GROUP BY ALL
), links AS (
  SELECT a, b FROM shared WHERE 100 * both_ >= 80 * (n_a + n_b - both_)
), reach(a, b) AS (
  SELECT a, b FROM links UNION SELECT r.a, l.b FROM reach r JOIN links l ON r.b = l.a
), lowest AS (
  SELECT a, min(b) AS low FROM reach GROUP BY a
)
SELECT s.doc_id, len(s.s) AS n_shingles, least(s.doc_id, coalesce(m.low, s.doc_id)) AS component_id,
       s.doc_id = least(s.doc_id, coalesce(m.low, s.doc_id)) AS kept
FROM sets s LEFT JOIN lowest m ON m.a = s.doc_id
"""


def oracle_sql() -> dict[str, str]:
    return {"op2_url_filter": OP2_SQL, "op4_vector_near_dedup": OP4_SQL, "op7_minhash_near_dedup": OP7_SQL}
