"""A training-data pipeline of five stages, each written and read again as the next one's input.

Every stage works on all rows its predecessor kept, and all but the last return the
columns of ``documents``. Each works row by row or by group on whatever it is given:
null texts are not in any language and go at the first stage; empty tables pass
through; extra columns stay.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from shiftscan import store
from shiftscan.llm import decontam, langid, minhash, mixing, queries, secrets
from shiftscan.store import stored

# Letters from which on a text's entropy is judged, and bits per symbol beyond which no known language has written it.
JUDGED_LETTERS, MOST_BITS = 200, 4.2
# The bits are those of alphabets; languages that write with more letters than this are not judged by them.
ALPHABET = 94
# Words of a shingle in stages that compare texts.
SHINGLE = 5


def _free(docs: DataFrame) -> str:
    """A column name that ``docs`` does not have."""
    name = "_found"
    while name in docs.columns:
        name += "_"
    return name


def language(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Rejects texts without letters, and long ones that no learned language explains better than chance."""
    name = _free(docs)
    got = langid.identify(docs, train=F.lit(True), into=name)
    letters = F.length(F.regexp_replace("text", r"\P{L}+", ""))
    chance = (F.col(f"{name}.bits") > MOST_BITS) & (F.col(f"{name}.alphabet") <= ALPHABET) & (letters >= JUDGED_LETTERS)
    return got.where((F.col(f"{name}.lang_pred") != langid.UNKNOWN) & ~chance).select(*docs.columns)


def near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of near copies stays: that with the smallest doc_id.

    Copies share 80 % of their five-word shingles; the query op7 has four words.
    """
    gone = minhash.near_duplicates(docs, size=SHINGLE).where("not kept and doc_id is not null").select("doc_id").distinct()
    return docs.join(gone, "doc_id", "left_anti").select(*docs.columns)


def benchmarks(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that hold a benchmark item go."""
    name = _free(docs)
    got = decontam.contamination(docs, spark.read.parquet(f"{sf_dir}/benchmark.parquet"), into=name)
    return got.where(F.size(name) == 0).select(*docs.columns)


def secret_free(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that hold a secret go."""
    name = _free(docs)
    return secrets.scan(docs, into=name).where(F.size(f"{name}.spans") == 0).select(*docs.columns)


def mixed(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The mixture, with the number of epochs that each document goes into."""
    return mixing.mix(docs, queries.mix_levels(), queries.MIX_WEIGHTS, fraction=0.6)


STAGES = [("language", language), ("near_duplicates", near_duplicates), ("benchmarks", benchmarks), ("secrets", secret_free), ("mixing", mixed)]
# Entropy, edit distance and seeded orders have no SQL form. Tests hold the first four stages against brute force on
# fixtures, and the last one's budgets and prefixes.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    before = store.mark(spark)
    for name, stage in STAGES:
        docs = stored(stage(spark, docs, sf_dir), f"stage-{name}")
        # What the stage has used, its input included, is not needed once it is written.
        store.clear(spark, before, keep_last=True)
    return docs
