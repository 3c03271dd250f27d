import random

import pyarrow as pa

from shiftscan.llm import decontam


def distance(a, b):
    """Least edit distance of a to any run of words of b."""
    row = [0] * (len(b) + 1)
    for i, x in enumerate(a):
        new = [i + 1]
        for j, y in enumerate(b):
            new.append(min(row[j + 1] + 1, new[j] + 1, row[j] + (x != y)))
        row = new
    return min(row)


def clean(text):
    return ["".join(c for c in w if c.isalnum()) for w in (text or "").lower().split() if any(c.isalnum() for c in w)]


def test_against_brute_force(spark):
    rng = random.Random(4)
    word = lambda: "".join(rng.choice("abcdefgh") for _ in range(rng.randrange(1, 5)))
    items = [(i, " ".join(word() for _ in range(n))) for i, n in enumerate([1, 2, 5, 9, 15, 20, 30, 45, 60, 12])] + [(50, ""), (51, None)]
    rows = []
    for i in range(150):
        words = [word() for _ in range(rng.randrange(80))]
        if i % 2:
            part = items[rng.randrange(3, 10)][1].split()
            for _ in range(rng.randrange(0, max(1, len(part) // 5))):
                part[rng.randrange(len(part))] = word()
            at = rng.randrange(len(words) + 1)
            words[at:at] = part
        rows.append((i, " ".join(w + rng.choice(["", "***", "!!"]) for w in words)))
    rows += [(200, None), (201, ""), (202, " ".join(items[7][1].upper().split()))]
    benchmark = spark.createDataFrame(items, "item_id long, text string")
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    got = {r.doc_id: set(r["items"]) for r in decontam.contamination(docs, benchmark).collect()}
    true = {(d, i) for d, t in rows for i, x in items if clean(x) and distance(clean(x), clean(t)) <= len(clean(x)) * 20 // 100}
    found = {(d, i) for d, s in got.items() for i in s}
    assert found <= true and len(found) >= 0.98 * len(true) and (202, 7) in found
    several = decontam.contamination(docs, benchmark, block_chars=300)
    assert {(r.doc_id, i) for r in several.collect() for i in r["items"]} <= true
    assert all(r["items"] == [] for r in decontam.contamination(docs, benchmark.limit(0)).collect())
    assert decontam.contamination(docs.limit(0), benchmark).count() == 0


def test_recall_under_edits():
    rng = random.Random(5)
    items = [(i, " ".join(f"w{rng.randrange(4000)}" for _ in range(rng.randrange(16, 50)))) for i in range(200)]
    index = decontam.Index(items, 20, 6, 11)
    texts = []
    for _, t in items:
        words = t.split()
        for _ in range(len(words) * 15 // 100):
            words[rng.randrange(len(words))] = "edited"
        texts.append(" ".join(["before"] * 10 + words + ["after"] * 10))
    got = index.matches(pa.array(texts))
    assert sum(i in g for (i, _), g in zip(items, got)) >= 0.95 * len(items)


def test_recall_at_the_full_limit():
    """Every item is found with as many edits as the limit allows, whatever its length."""
    rng = random.Random(6)
    for n in (1, 3, 5, 8, 10, 12, 15, 16, 20, 40, 60, 200):
        items = [(i, " ".join(f"w{rng.randrange(4000)}" for _ in range(n))) for i in range(60)]
        index = decontam.Index(items, 20, 6, 11)
        texts = []
        for i, t in items:
            words = t.split()
            if i % 2:
                for k in rng.sample(range(n), n * 20 // 100):
                    words[k] = "edited"
            else:
                for _ in range(n * 20 // 100):
                    k = rng.randrange(len(words))
                    words[k : k + 1] = rng.choice([["edited"], [], [words[k], "added"]])
            texts.append(" ".join(["before"] * 10 + words + ["after"] * 10))
        got = index.matches(pa.array(texts))
        assert all(i in g for (i, _), g in zip(items, got)), n
