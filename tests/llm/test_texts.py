"""Licenses, surrogates and languages."""

import zlib

import pytest
from pyspark.sql import functions as F

from shiftscan.llm import langid, licenses, queries, surrogates

SMALL = "/root/testdata/sf0.01"
KEY = b"test key of 16 bytes"


def test_licenses(spark):
    rows = [
        (1, "words\nReleased under the MIT License.\nmore"), (2, "Licensed under CC BY-NC 4.0."), (3, "Licensed under the Apache License, Version 1.1."), (4, "he lost his license to drive"), (5, None), (6, ""),
        (7, "This work is licensed under the GNU General Public License, version 2.\n\nLicensed under the Apache License, Version 2.0."), (8, "x " * 50_000 + "\nReleased*** under the MIT### License."),
    ]
    docs = spark.createDataFrame(rows, "doc_id long, text string").withColumn("license", F.lit("clash"))
    got = {r.doc_id: [x.license for x in r.licenses] for r in licenses.scan(docs).collect()}
    assert got == {1: ["MIT"], 2: ["CC-BY-NC-4.0"], 3: [None], 4: [None], 5: [], 6: [], 7: ["GPL-2.0", "Apache-2.0"], 8: ["MIT"]}
    span = licenses.scan(docs).where("doc_id = 1").first().licenses[0]
    assert rows[0][1][span.start : span.end] == "Released under the MIT License." and not span.differences
    assert licenses.scan(docs.limit(0)).count() == 0


def test_wrapped_licenses():
    """Notices as files hold them: wrapped, in comments, with headings and identifiers."""
    mit = "MIT License\n\nCopyright (c) 2020 Someone\n\nPermission is hereby granted, free of charge, to any person obtaining a copy\nof this software and associated documentation files (the \"Software\"), to deal\nin the Software without restriction, including without limitation the rights\nto use, copy, modify, merge, publish, distribute, sublicense, and/or sell\ncopies of the Software.\n"
    bsd = "Copyright 2019 Someone\n\nRedistribution and use in source and binary forms, with or without\nmodification, are permitted provided that the following conditions\nare met:\n"
    broken = "// Redistribution and use in source and binary forms,\n//\n// with or without modification, are permitted redistribution\n//\n// provided that the following conditions are met (license)\n"
    names = lambda text: [x["license"] for x in licenses._scanner(0.2).scan(text) if x["license"]]
    assert names(mit) == ["MIT", "MIT"] and names(bsd) == ["BSD-3-Clause"] and names(broken) == ["BSD-3-Clause"]
    assert names(mit + "\n" + bsd) == ["MIT", "MIT", "BSD-3-Clause"]
    assert names("".join(f"# {x}\n" for x in mit.split("\n"))) == ["MIT", "MIT"]
    for name, ids in licenses.SPDX.items():
        assert all(names(f"// SPDX-License-Identifier: {x}\nint main;") == [name] for x in ids)
    assert names("                    GNU GENERAL PUBLIC LICENSE\n                       Version 3, 29 June 2007\n") == ["GPL-3.0"]
    assert names("SPDX-License-Identifier: Zlib") == [] and names("a license\nof other words") == []


def test_surrogates(spark):
    text = "Mail ann.lee@corp.example.com or ANN.lee@Corp.example.com, +1 (521) 555-6210, 10.20.30.40, 4785 3805 9239 1139; Mrs. Anna Berg met Иван and Dr. Müller."
    new, kinds = surrogates.replaced(text, KEY)
    assert kinds == ["email", "email", "phone", "ip", "card", "name", "name", "name"]
    for old in ("ann.lee", "555-6210", "10.20.30.40", "4785 3805", "Anna", "Иван", "Müller"):
        assert old not in new
    assert len(new.split()) == len(text.split()) and "Mrs. " in new and new.count("@") == 2
    a, b = (w.lower() for w in new.replace(",", "").split() if "@" in w)
    assert a == b
    assert any(f"Mrs. {n}" in new for n in surrogates.NAMES["latin", "f"]) and any(n in new for n in surrogates.NAMES["cyrillic", "m"])
    for kind, form in (("card", "{:016d}"), ("phone", "+1 (212) 555-{:04d}"), ("name", "Zz{:04d}")):
        some = [form.format(i) for i in range(3000)]
        assert len({surrogates.surrogate(kind, s, KEY) for s in some}) == 3000
    assert {len(set(map(lambda x: surrogates._ip(x, KEY), [f"1.2.{i}.{j}" for i in range(50) for j in range(50)])))} == {2500}
    docs = spark.createDataFrame([(1, text), (2, None), (3, ""), (4, "clean words only"), (5, text)], "doc_id long, text string")
    got = {r.doc_id: r.text for r in surrogates.pseudonymise(docs, KEY).collect()}
    assert got[1] == got[5] == new and got[2] is None and got[3] == "" and got[4] == "clean words only"
    assert surrogates.collisions(surrogates.found(spark.read.parquet(f"{SMALL}/documents.parquet"), KEY)).count() == 0
    clash = docs.withColumns({"kinds": F.lit("x"), "_new": F.lit("y"), "new": F.lit("z")})
    assert surrogates.pseudonymise(clash, KEY).where("doc_id = 1 and size(kinds) = 8 and _new = 'y' and new = 'z'").count() == 1
    for key in (b"short", "not bytes, however long"):
        with pytest.raises(ValueError, match="key"):
            surrogates.pseudonymise(docs, key)


def test_surrogates_are_a_permutation_without_fixed_points():
    """Whole forms by brute force: every string goes to another one of the form, and none to the same."""
    import itertools

    letters = "abcdefghijklmnopqrstuvwxyz"
    every = ["".join(x).title() for x in itertools.product(letters, repeat=2)]
    got = [surrogates.surrogate("name", x, KEY) for x in every]
    assert sorted(got) == sorted(every) and all(a != b for a, b in zip(every, got))
    sound = lambda x: [c in surrogates.VOWELS for c in x.lower()]
    assert all(sound(a) == sound(b) for a, b in zip(every, got))
    phones = [f"555-{i:04d}" for i in range(10_000)]
    got = [surrogates.formatted(x, KEY, "phone") for x in phones]
    assert len(set(got)) == 10_000 and all(a != b for a, b in zip(phones, got))
    for n, first in ((16, 4_000_000_000_000_000), (15, 340_000_000_000_000)):
        cards = [str(first + i) for i in range(400)]
        got = [surrogates.surrogate("card", x, KEY) for x in cards]
        assert len(set(got)) == 400 and all(a != b and len(b) == n for a, b in zip(cards, got))
        assert [surrogates.checksum(x) for x in got] == [surrogates.checksum(x) for x in cards]
    both = ["1.2.3.4", "01.2.3.4", "001.2.3.4", "10.0.0.1", "10.00.0.1"]
    assert len({surrogates.surrogate("ip", x, KEY) for x in both}) == 5
    assert surrogates.checksum("4111 1111 1111 1111") and not surrogates.checksum("4111 1111 1111 1112")


def test_names_beyond_the_lists():
    new = lambda text, **o: surrogates.replaced(text, KEY, **o)
    text = "My name is Priya Sharma. Contact: Wei Chen. Later Sharma wrote to Chen; the Sharma family knows Dr. Okafor, and Okafor knows them."
    out, kinds = new(text)
    assert kinds == ["name"] * 7
    assert not any(x in out for x in ("Priya", "Sharma", "Wei", "Chen", "Okafor"))
    where = [w for w in out.replace(".", "").replace(";", "").replace(",", "").split()]
    old = [w for w in text.replace(".", "").replace(";", "").replace(",", "").split()]
    same = {a: b for a, b in zip(old, where)}
    assert all(same[a] == b for a, b in zip(old, where))  # one word, one surrogate
    assert new("Kofi Mensah went out")[1] == [] and new("Kofi Mensah went out", more=("Kofi",))[1] == ["name"]
    assert new("Dear Sir, the New York office. Contact us.") == ("Dear Sir, the New York office. Contact us.", [])
    assert new("Mr Ωμέγα and 王@例え.jp")[0] != "Mr Ωμέγα and 王@例え.jp"
    long = "Dr. Brown 10.0.0.1 " * 20_000
    assert len(new(long)[1]) == 40_000


def brute(samples, text):
    """Cross-parsing by substring search."""
    clean = lambda t: " ".join("".join(c if c.isalpha() else " " for c in t.lower()).split())
    text = clean(text)
    out = {}
    for lang, sample in samples.items():
        sample, at, phrases = clean(sample), 0, 0
        while at < len(text):
            n = 1
            while at + n < len(text) and text[at : at + n + 1] in sample:
                n += 1
            at, phrases = at + n, phrases + 1
        out[lang] = phrases
    return out


def test_cross_parsing():
    samples = {"aa": "the cat sat on the mat and the dog ran after the cat", "bb": "le chat est sur la table et le chien court dans la rue"}
    parser = langid.Parser(tuple(sorted(samples.items())), 96, 1024)
    for text in ("the dog sat", "le chien est sur la rue", "cat table dog rue", "a", "xyz"):
        cost, _ = parser.costs([text])
        phrases = (cost[0] * len(text) / parser.bits).round().astype(int).tolist()
        assert phrases == list(brute(samples, text).values())


def test_languages(spark, tmp_path):
    docs = spark.read.parquet(f"{SMALL}/documents.parquet")
    odd = spark.createDataFrame([(90_001, None, "en"), (90_002, "", "en"), (90_003, "123 !!", "de"), (90_004, "le " * 40_000, None)], "doc_id long, text string, lang string")
    docs.select("doc_id", "text", "lang").union(odd).write.parquet(f"{tmp_path}/documents.parquet")
    got = {r.doc_id: r for r in queries.op10_cross_parsing_language(spark, str(tmp_path)).collect()}
    assert [got[d].lang_pred for d in (90_001, 90_002, 90_003, 90_004)] == ["und", "und", "und", "fr"]
    held = [r for r in docs.collect() if zlib.crc32(str(r.doc_id).encode()) % 4 == 2]
    assert all(got[r.doc_id].held_out for r in held) and all(0 <= r.score <= 1 for r in got.values())
    assert sum(got[r.doc_id].lang_pred == r.lang for r in held) >= 0.98 * len(held)
    none = langid.identify(docs.limit(0), F.lit(True))
    assert none.count() == 0


def test_large_scripts(spark):
    """Two languages of a large script and one of a small: each letter counts, however many there are."""
    rng = __import__("random").Random(3)
    words = {lang: ["".join(chr(0x4E00 + rng.randrange(low, low + 1500)) for _ in range(2)) for _ in range(600)] for lang, low in (("xa", 0), ("xb", 700))}
    words["en"] = ["".join(rng.choice("abcdefghij") for _ in range(5)) for _ in range(600)]
    text = lambda lang, n: " ".join(rng.choice(words[lang]) for _ in range(n))
    rows = [(k, text(lang, 2000), lang) for k, lang in enumerate(words)] + [(10 + k, text(lang, 120), lang) for k, lang in enumerate([*words] * 10)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string")
    got = langid.identify(docs, F.col("doc_id") < 10).where("doc_id >= 10").collect()
    assert all(r.language.lang_pred == r.lang for r in got)
    assert all((r.language.alphabet > 94) == (r.lang != "en") for r in got)
    parser = langid.Parser(tuple((r[2], r[1]) for r in sorted(rows[:3], key=lambda r: r[2])), 96, 1024)
    whole = langid.Parser(tuple((r[2], r[1]) for r in sorted(rows[:3], key=lambda r: r[2])), 5000, 1024)
    assert (parser.costs([r[1] for r in rows[3:]])[0] == whole.costs([r[1] for r in rows[3:]])[0]).all()
