"""Secret spans against Python's own matcher, and the battery on known strings."""

import hashlib
import random
import re

from pyspark.sql import functions as F

from shiftscan.llm import queries, secrets

SMALL = "/root/testdata/sf0.001"
ASSIGN = re.compile(r"""(password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", re.I | re.A)


def base(text):
    text = text or ""
    out = [(m.start(), 0, m.end()) for m in ASSIGN.finditer(text) if len(m[2]) >= 6]
    out += [(m.start(), 1, m.end()) for m in re.finditer("AKIA[A-Z0-9]+", text) if len(m[0]) >= 20]
    out += [(m.start(), 2, m.end()) for m in re.finditer("[0-9a-f]+", text) if len(m[0]) >= 24]
    return sorted(out)


def written(spans):
    return ",".join(f"{secrets.KINDS[k]}:{a}:{b}" for a, k, b in spans)


def test_query(spark, tmp_path):
    rng = random.Random(5)
    bits = ["token", "secret", "API_KEY", "apikey", "password", "=", ":", " ", '"', "'", "abc", "x1", "é", "𝒳", "deadbeef" * 3, "AKIA", "ABCD1234" * 2, "\n", "a.b-c", "passwd=", "zzzzzz"]
    rows = [(i, "".join(rng.choice(bits) for _ in range(rng.randrange(40)))) for i in range(400)]
    rows += [(400, None), (401, ""), (402, "token=abcdef " * 3000), (403, "secret=token = abcdefgh"), (None, "token: abcdefg"), (400, "passwd:longenough")]
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    docs.withColumn("lang", F.lit("en")).write.parquet(f"{tmp_path}/documents.parquet")
    got = queries.op5_secret_scan(spark, str(tmp_path)).collect()
    want = sorted((d is None, d or 0, hashlib.sha256(written(base(t)).encode()).hexdigest()) for d, t in rows)
    assert sorted((r.doc_id is None, r.doc_id or 0, r.base_sha256) for r in got) == want
    by = {r.doc_id: r for r in got if r.doc_id != 400}
    for d, t in rows:
        if d != 400:
            kinds = [k for _, k, _ in base(t)]
            assert (by[d].n_assign, by[d].n_access, by[d].n_hex) == tuple(kinds.count(k) for k in range(3))


def test_battery(spark):
    rng = random.Random(1)
    drawn = ["".join(rng.choice("0123456789abcdef") for _ in range(40)) for _ in range(200)]
    drawn += ["".join(rng.choice(secrets.DIGITS + secrets.UPPER + secrets.LOWER) for _ in range(48)) for _ in range(200)]
    plain = ["0123456789abcdef" * 3, "a1" * 20, "the-quick-brown-fox2-jumps-over-the-lazy-dog"]
    rows = [("drawn", t) for t in drawn] + [("plain", t) for t in plain]
    got = spark.createDataFrame(rows, "k string, t string").select("k", secrets.p_random(F.col("t")).alias("p")).collect()
    p = [r.p for r in got if r.k == "drawn"]
    assert 0.3 < sum(p) / len(p) < 0.7 and sum(x < 0.01 for x in p) < 15
    assert all(r.p < 1e-4 for r in got if r.k == "plain")


def test_added_spans(spark):
    rng = random.Random(2)
    secret = "".join(rng.choice(secrets.DIGITS + secrets.UPPER + secrets.LOWER) for _ in range(50))
    rows = [(1, f"see {secret} here"), (2, "plain words only"), (3, f"token = {secret}"), (4, "zq9" * 20), (5, "onlylettersonlylettersonlyletters")]
    docs = spark.createDataFrame(rows, "doc_id long, text string").withColumn("kind", F.lit(1))
    got = {r.doc_id: [tuple(s) for s in r.secrets.spans] for r in secrets.scan(docs).collect()}
    assert got[1] == [(4, 3, 54)] and not got[2] and not got[4] and not got[5]
    assert [k for _, k, _ in got[3]] == [0]
    assert secrets.scan(docs.limit(0)).count() == 0


def test_values_in_context(spark):
    """Random values after a name, in a query, with padding, next to other encodings' characters, and short ones."""
    rng = random.Random(8)
    draw = lambda n, more="": "".join(rng.choice(secrets.DIGITS + secrets.UPPER + secrets.LOWER + more) for _ in range(n))
    plain, base64, short = draw(40), draw(42, "+/") + "==", draw(20)
    rows = [(1, "SIGNATURE=", plain, " ok"), (2, "https://a.example/get?sig=", plain, "&x=1"), (3, "a_long_name_of_some_kind2=", base64, "\nnext"), (4, "my-own-", draw(30) + "+" + draw(12), " end"), (5, "id ", short, "."), (6, "é path/", draw(30) + "-" + draw(9), "/x")]
    docs = spark.createDataFrame([(i, a + b + c) for i, a, b, c in rows], "doc_id long, text string")
    got = {r.doc_id: {tuple(s) for s in r.secrets.spans} for r in secrets.scan(docs).collect()}
    for i, a, b, _ in rows:
        assert any(k == 3 and lo <= len(a) and len(a + b) <= hi for lo, k, hi in got[i]), (i, got[i])
    assert got[1] == {(10, 3, 50)} and got[5] == {(3, 3, 23)}


def test_share_of_false_secrets_by_length(spark):
    """Drawn tokens and identifiers of words and numbers, in prose: what is reported is drawn, and long drawn tokens are all found."""
    rng = random.Random(1)
    letters = secrets.DIGITS + secrets.UPPER + secrets.LOWER
    prose = [r.text for r in spark.read.parquet("/root/testdata/sf0.01/documents.parquet").where("length(text) > 300").orderBy("doc_id").limit(200).collect()]
    parts = ["blue", "getUser", "data", "House", "file", "River", "value", "Item", "index", "Stone", "total", "green", "Market"]
    rows = []
    for n in (18, 28, 40, 64, 100):
        for drawn in (True, False) * 40:
            token = "".join(rng.choice(letters) for _ in range(n)) if drawn else "".join(rng.sample(parts * 2, 26))[: n - 3] + str(rng.randrange(100, 999))
            text = rng.choice(prose)
            rows.append((n, drawn, f"{text[:150]} {token} {text[150:]}"))
    got = secrets.scan(spark.createDataFrame(rows, "n int, drawn boolean, text string")).withColumn("hit", F.exists("secrets.spans", lambda s: s.kind == 3)).collect()
    for n in (18, 28, 40, 64, 100):
        hits = {d: sum(r.hit for r in got if r.n == n and r.drawn == d) for d in (True, False)}
        assert hits[False] <= 0.1 * (hits[True] + hits[False]), (n, hits)
        assert n < 40 or hits[True] == 40


def test_clashing_column(spark):
    docs = spark.createDataFrame([(1, "token=abcdefgh")], "doc_id long, text string").withColumns({"secrets": F.lit("x"), "class": F.lit(1), "decoy": F.lit(2)})
    got = secrets.scan(docs).first()
    assert got["class"] == 1 and got.decoy == 2 and len(got.secrets.spans) == 1
    assert secrets.scan(docs, into="own").first().secrets == "x"
