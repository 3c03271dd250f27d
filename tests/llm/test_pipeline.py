"""Stages against what each must leave, and the guard of the entry point."""

import math
import random
import re

from pyspark.sql import functions as F

import corpus_pipeline
from shiftscan.llm import components, langid

SMALL = "/root/testdata/sf0.001"


def test_stages(spark):
    docs = spark.read.parquet(f"{SMALL}/documents.parquet")
    columns, before = docs.columns, docs.count()
    kept = docs
    for name, stage in corpus_pipeline.STAGES[:-1]:
        kept = corpus_pipeline.stored(stage(spark, kept, SMALL), name)
        assert kept.columns == columns
        assert kept.count() <= before
        before = kept.count()
    assert before > 0.5 * docs.count()
    last = corpus_pipeline.STAGES[-1][1](spark, kept, SMALL)
    assert set(columns) <= set(last.columns) and 0 < last.count() <= before
    odd = spark.createDataFrame([(1, None, "en", "s", 0), (2, "", None, None, None), (None, "token = abcdefgh words", "en", "src1", 1), (2, "the of and", "en", "src1", 1), (2, "the of and", "en", "src1", 1)], docs.schema)
    for some in (odd, odd.limit(0)):
        for _, stage in corpus_pipeline.STAGES:
            some = corpus_pipeline.stored(stage(spark, some, SMALL), "odd")
        some.collect()


def test_components(spark):
    links = [(i, i + 1) for i in range(1, 40)] + [(100, 101), (101, 100), (7, 7), (500, 500), (60, 50), (70, 60), (None, 3)]
    got = {r.id: r.component for r in components.components(spark.createDataFrame(links, "a long, b long")).collect()}
    assert {got[i] for i in range(1, 41)} == {1} and got[101] == 100 and got[500] == 500 and got[70] == 50


def test_near_duplicates_by_five_words(spark):
    """The stage against all pairs of five-word sets, with a pair that is near on four words only."""
    base = [f"w{i}" for i in range(40)]
    texts = {1: base, 2: [*base[:20], "new", *base[21:]], 3: [f"v{i}" for i in range(60)], 5: ["a", "b"], 6: ["a", "b"], 7: ["a", "c"]}
    texts[4] = [*texts[3][:30], "new", *texts[3][31:]]
    sets = {d: {tuple(w[i : i + 5]) for i in range(len(w) - 4)} or {tuple(w)} for d, w in texts.items()}
    gone = {b for a in texts for b in texts if a < b and len(sets[a] & sets[b]) >= 0.8 * len(sets[a] | sets[b])}
    assert gone == {4, 6}
    docs = spark.createDataFrame([(d, " ".join(w), "en", "s", 0) for d, w in texts.items()], "doc_id long, text string, lang string, source string, n_chars long")
    assert {r.doc_id for r in corpus_pipeline.near_duplicates(spark, docs, SMALL).collect()} == set(texts) - gone


def table(spark, texts):
    return spark.createDataFrame([(d, t, "en", "src1", 0) for d, t in texts.items()], "doc_id long, text string, lang string, source string, n_chars long")


def test_language_stage_by_brute_force(spark):
    """Bits a symbol by substring search: texts in the sample's language stay, letters drawn at random go."""
    rng = random.Random(9)
    words = ["".join(rng.choice("etaoinshrdlu") for _ in range(rng.randrange(2, 7))) for _ in range(60)]
    texts = {k: " ".join(rng.choice(words) for _ in range(45)) for k in range(12)}
    texts |= {20 + k: "".join(rng.choice("abcdefghijklmnopqrstuvwxyz") for _ in range(260)) for k in range(4)}
    texts |= {30: "zxqj vkwp", 31: "12 34", 32: None, 33: ""}
    docs = table(spark, texts).withColumn("lang", F.when(F.col("doc_id") < 12, "en"))
    (lang, sample), = langid.samples_of(docs, F.lit(True), 200, 30_000)
    clean = lambda t: " ".join("".join(c if c.isalpha() else " " for c in (t or "").lower()).split())
    known = clean(sample)
    want = set()
    for d, t in texts.items():
        t = clean(t)
        if not t:
            continue
        at = phrases = 0
        while at < len(t):
            n = 1
            while at + n < len(t) and t[at : at + n + 1] in known:
                n += 1
            at, phrases = at + n, phrases + 1
        bits = phrases * math.log2(len(known)) / len(t)
        if len(t.replace(" ", "")) < corpus_pipeline.JUDGED_LETTERS or bits <= corpus_pipeline.MOST_BITS:
            want.add(d)
    assert want == {*range(12), 30}
    assert {r.doc_id for r in corpus_pipeline.language(spark, docs, SMALL).collect()} == want


def test_benchmark_and_secret_stages_by_brute_force(spark, tmp_path):
    rng = random.Random(10)
    word = lambda: "".join(rng.choice("abcdefgh") for _ in range(rng.randrange(2, 6)))
    items = [[word() for _ in range(n)] for n in (8, 15, 30)]
    texts = {}
    for d in range(60):
        own = [word() for _ in range(40)]
        if d % 2:
            part = rng.choice(items).copy()
            for _ in range(rng.randrange(0, len(part) // 3)):
                part[rng.randrange(len(part))] = word()
            own[10:10] = part
        texts[d] = " ".join(own) + ("" if d % 5 else rng.choice([" token = abcdefgh1", " AKIA" + "Q1W2" * 4, " " + "09af" * 6, " token=abc", " AKIA12"]))
    spark.createDataFrame([(k, " ".join(x)) for k, x in enumerate(items)], "item_id long, text string").write.parquet(f"{tmp_path}/benchmark.parquet")
    docs = table(spark, texts)

    def distance(a, b):
        row = [0] * (len(b) + 1)
        for i, x in enumerate(a):
            new = [i + 1]
            for j, y in enumerate(b):
                new.append(min(row[j + 1] + 1, new[j] + 1, row[j] + (x != y)))
            row = new
        return min(row)

    clear = {d for d, t in texts.items() if all(distance(x, [w for w in t.replace("=", "").split()]) > len(x) * 20 // 100 for x in items)}
    assert {r.doc_id for r in corpus_pipeline.benchmarks(spark, docs, str(tmp_path)).collect()} == clear and 30 <= len(clear) < 60
    base = re.compile(r"""(?i:password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?[A-Za-z0-9+/_.=-]{6,}|AKIA[A-Z0-9]{16,}|[0-9a-f]{24,}""")
    free = {d for d, t in texts.items() if not base.search(t)}
    assert {r.doc_id for r in corpus_pipeline.secret_free(spark, docs, SMALL).collect()} == free


def test_inner_names_do_not_clash(spark):
    docs = table(spark, {1: "the one and only text of a few words", 2: "token = abcdefgh", 3: "another text of words"}).withColumns({n: F.lit(n) for n in ("_items", "_secrets", "_language", "component_id", "kept")})
    for _, stage in corpus_pipeline.STAGES[:-1]:
        got = stage(spark, docs, SMALL)
        assert got.columns == docs.columns and all(r._items == "_items" and r._language == "_language" and r._secrets == "_secrets" for r in got.collect())
