"""Secrets in texts: fixed patterns, and a battery of randomness tests.

Patterns give the base spans. The method adds tokens that look drawn at random: for
each token of 16 characters or more an encoding is inferred, and three tests of randomness over that
encoding's alphabet are made: chi-squared uniformity, the number of runs above and
below the middle symbol, and the lag-one serial correlation. Fisher's rule combines
them into one p-value. Tokens whose p-value reaches their length class's threshold are
secrets.

The threshold bounds the share of false secrets. Every token has ``DECOYS`` ordinary
strings of its length, written from words of its own text and a number, and they pass
the same battery. At a threshold, the decoys that reach it, by their number, tell how
many ordinary tokens would; the lowest threshold is taken at which these are at most
``fdr`` of the tokens that reach it. Where a class's tokens are too short for the battery to tell
them from words, that is high, or there is none and the class adds nothing.

A token is a run of characters that encodings use, with ``=`` at its end only, so names
and values are apart. A run that mixes the special characters of two encodings fits
none: the runs of either within it are its tokens. Of secrets within another only the
outer one is reported.

Everything is built-in column expressions. The only shuffle is of two histograms of
p-values (``BINS`` by length class: bounded whatever the input); their thresholds are a
handful of numbers. Offsets are code points, ends exclusive.

Defined results: a null text is empty and has no spans; rows are judged one by one, so
repeated rows and missing ids are no special case; an empty table gives an empty
result; columns of ``docs`` are kept, and the result goes into one struct column whose
name is a parameter. Cost is linear in a text's length but for a factor of at most
``_BLOCK`` in its number of matches.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import need, text_of

# The base patterns, the least lengths, and the encodings' alphabets.
ASSIGN = r"""(?i)(password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)"""
ACCESS = r"AKIA[A-Z0-9]{16,}"
HEX = r"[0-9a-f]{24,}"
LEAST_VALUE = 6
KINDS = ("assign", "access", "hex", "random")
# Padding stands at the end; tokens without a digit or without a letter are no secrets and are not looked at.
_PAD = r"(?:=+(?![A-Za-z0-9+/_=-]))?"
TOKEN = r"(?<![A-Za-z0-9+/_-])(?=[A-Za-z+/_-]*[0-9])(?=[0-9+/_-]*[A-Za-z])[A-Za-z0-9+/_-]{16,}" + _PAD
MIXED = r"[+/].*[_-]|[_-].*[+/]"
PARTS = (r"[A-Za-z0-9+/]{16,}" + _PAD, r"[A-Za-z0-9_-]{16,}" + _PAD)
ANY = r"(?i:passw|secret|token|api_?key)|AKIA|[A-Za-z0-9+/_=-]{24}"
DIGITS, LOWER, UPPER = "0123456789", "abcdefghijklmnopqrstuvwxyz", "ABCDEFGHIJKLMNOPQRSTUVWXYZ"
ENCODINGS = (
    ("hex", r"^[0-9a-f]+$", DIGITS + "abcdef"),
    ("HEX", r"^[0-9A-F]+$", DIGITS + "ABCDEF"),
    ("base32", r"^[A-Z2-7]+=*$", UPPER + "234567"),
    ("base36", r"^[a-z0-9]+$", DIGITS + LOWER),
    ("base62", r"^[A-Za-z0-9]+$", DIGITS + UPPER + LOWER),
    ("base64url", r"^[A-Za-z0-9_-]+=*$", UPPER + LOWER + DIGITS + "-_"),
    ("base64", r"^[A-Za-z0-9+/]+=*$", UPPER + LOWER + DIGITS + "+/"),
)
CLASSES = (16, 24, 32, 48, 96)  # least lengths of the length classes
BINS = 2000
DECOYS = 20
_NUMBER = 3  # digits at a decoy's end
_FILLER = "ordinarywordsthatstandinarow"  # for texts without other words
_BLOCK = 128
_SPAN = "array<struct<start: int, kind: int, end: int, token: string>>"


def _let(value: Column, use) -> Column:
    """``use(value)`` with the value worked out once per row."""
    return F.transform(F.array(value), use)[0]


def _sum(numbers: Column, kind: str = "int") -> Column:
    return F.aggregate(numbers, F.lit(0).cast(kind), lambda a, x: a + x.cast(kind))


def _spans(text: Column, pattern: str, kind: int, group: int = 0, least: int = 0) -> Column:
    """Spans of the leftmost matches whose ``group`` has ``least`` characters at least."""
    expr = F.lit(pattern)
    found = F.struct(F.regexp_extract_all(text, expr, F.lit(0)).alias("hit"), F.regexp_extract_all(text, expr, F.lit(group)).alias("value"), F.split(text, pattern, -1).alias("gap"))

    def placed(x: Column) -> Column:
        """Where each match ends: running sums by blocks, then within a block."""
        step = F.transform(x.hit, lambda h, i: F.length(h) + F.length(F.get(x.gap, i)))
        return _let(step, lambda s: _let(F.transform(F.sequence(F.lit(0), (F.size(s) / _BLOCK).cast("int")), lambda b: _sum(F.slice(s, b * _BLOCK + 1, F.lit(_BLOCK)))), lambda sums: _let(F.transform(sums, lambda _, b: _sum(F.slice(sums, F.lit(1), b))), lambda base: F.transform(s, lambda _, i: F.get(base, (i / _BLOCK).cast("int")) + _sum(F.slice(s, (i / _BLOCK).cast("int") * _BLOCK + 1, i % _BLOCK + 1))))))

    def built(x: Column) -> Column:
        return _let(placed(x), lambda to: F.filter(F.transform(x.hit, lambda h, i: F.when(F.length(F.get(x.value, i)) >= least, F.struct((F.get(to, i) - F.length(h)).alias("start"), F.lit(kind).alias("kind"), F.get(to, i).alias("end"), h.alias("token")))), lambda y: y.isNotNull()))

    empty = F.array().cast(_SPAN)
    return _let(found, lambda x: F.when(F.size(x.hit) > 0, built(x)).otherwise(empty)).cast(_SPAN)


def _tokens(text: Column) -> Column:
    """Spans of the tokens to test, or null."""

    def parts(y: Column) -> Column:
        inner = _let(y.token, lambda t: F.array_distinct(F.concat(*(_spans(t, pattern, 3) for pattern in PARTS))))
        moved = F.transform(inner, lambda z: F.struct((z.start + y.start).alias("start"), z.kind.alias("kind"), (z.end + y.start).alias("end"), z.token.alias("token")))
        return F.when(y.token.rlike(MIXED), moved).otherwise(F.array(y)).cast(_SPAN)

    return F.when(text.rlike(TOKEN), F.flatten(F.transform(_spans(text, TOKEN, 3), parts)))


def _upper_tail(z: Column) -> Column:
    """The standard normal's upper tail, by a logistic fit good to two parts in 10,000."""
    z = F.least(F.greatest(z, F.lit(-12.0)), F.lit(12.0))
    return 1 / (1 + F.exp(1.5976 * z + 0.07056 * z * z * z))


def p_random(token: Column) -> Column:
    """p-value of the battery under the hypothesis that the token is random; null if no encoding fits."""

    def battery(x: Column) -> Column:
        s, alphabet, sides = x.s, x.alphabet, x.sides
        n, size = F.length(s).cast("double"), F.length(alphabet).cast("double")
        squares = F.aggregate(F.split(alphabet, ""), F.lit(0.0), lambda a, c: a + F.pow(n - F.length(F.replace(s, c, F.lit(""))), F.lit(2.0)))

        def uniform(y: Column) -> Column:
            chi, df = y * size / n - n, size - 1
            return (F.pow(F.greatest(chi, F.lit(0.0)) / df, F.lit(1 / 3)) - (1 - 2 / (9 * df))) / F.sqrt(2 / (9 * df))

        def runs(b: Column) -> Column:
            high = F.length(F.replace(b, F.lit("L"), F.lit(""))).cast("double")
            turns = (2 * n - F.length(F.replace(b, F.lit("LH"), F.lit(""))) - F.length(F.replace(b, F.lit("HL"), F.lit("")))) / 2
            spread = lambda m: (m - 1) * (m - 2) / (n - 1)
            return _let(2 * high * (n - high) / n + 1, lambda mean: F.when((mean > 2) & (n > 1), (turns + 1 - mean) / F.sqrt(spread(mean))).otherwise(F.lit(12.0)))

        def serial(y: Column) -> Column:
            mean = F.aggregate(y, F.lit(0.0), lambda a, v: a + v) / n
            return _let(
                _let(mean, lambda m: F.transform(y, lambda v: v - m)),
                lambda d: _let(F.aggregate(d, F.lit(0.0), lambda a, v: a + v * v), lambda var: F.when(var > 0, F.aggregate(F.zip_with(F.slice(d, F.lit(1), F.size(d) - 1), F.slice(d, F.lit(2), F.size(d) - 1), lambda a, b: a * b), F.lit(0.0), lambda a, v: a + v) / var * F.sqrt(n)).otherwise(F.lit(12.0))),
            )

        codes = F.transform(F.split(s, ""), lambda c: F.call_function("instr", alphabet, c).cast("double"))
        scores = F.array(
            _let(squares, uniform),
            F.abs(_let(F.call_function("translate", s, alphabet, sides), runs)),
            F.abs(_let(codes, serial)),
        )
        # The last two tests are two-sided. Fisher: twice the sum is chi-squared with six degrees of freedom.
        logs = F.transform(scores, lambda z, i: -F.log(F.greatest(F.least(_let(z, _upper_tail) * F.when(i > 0, 2.0).otherwise(1.0), F.lit(1.0)), F.lit(1e-300))))
        return _let(F.aggregate(logs, F.lit(0.0), lambda a, v: a + v), lambda y: F.exp(-y) * (1 + y + y * y / 2))

    fits = F.lit(None).cast("struct<alphabet: string, sides: string>")
    for _, pattern, alphabet in reversed(ENCODINGS):
        half = len(alphabet) // 2
        fits = F.when(token.rlike(pattern), F.struct(F.lit(alphabet).alias("alphabet"), F.lit("L" * half + "H" * (len(alphabet) - half)).alias("sides"))).otherwise(fits)
    found = _let(fits, lambda e: F.struct(F.rtrim(token, F.lit("=")).alias("s"), e.alphabet.alias("alphabet"), e.sides.alias("sides")))
    out = _let(found, lambda x: F.when(x.alphabet.isNotNull(), battery(x)))
    # Words and plain numbers are no secrets however they are spread.
    mixed = token.rlike("[0-9]") & token.rlike("[A-Za-z]")
    return F.when(mixed, out)


def _class(token: Column) -> Column:
    out = F.lit(0)
    for k, least in enumerate(CLASSES):
        out = F.when(F.length(token) >= least, k).otherwise(out)
    return out


def _trials(docs: DataFrame) -> DataFrame:
    """(class, decoy, p) of every token to test and of its decoys; ``docs``: (text)."""
    text = F.col("text")
    words = F.regexp_replace(F.regexp_replace(text, TOKEN, " "), "[^A-Za-z]", "")
    rows = docs.where(text.rlike(TOKEN)).select(_tokens(text).token.alias("tokens"), F.when(words == "", F.lit(_FILLER)).otherwise(words).alias("words"))
    each = rows.select(F.explode("tokens").alias("token"), "words").withColumn("n", F.length("token"))
    # At least one decoy's length, whatever the text.
    each = each.withColumn("words", F.expr("repeat(words, 1 + cast(n / length(words) as int))"))

    def decoy(j: Column) -> Column:
        at = F.pmod(j * (F.col("n") + 7), F.greatest(F.length("words") - F.col("n"), F.lit(1)))
        return F.concat(F.substr("words", at + 1, F.col("n") - _NUMBER), F.lpad(F.pmod(F.crc32(F.concat_ws(":", F.col("token"), j).cast("binary")), F.lit(10**_NUMBER)).cast("string"), _NUMBER, "0"))

    made = F.transform(F.sequence(F.lit(0), F.lit(DECOYS - 1)), lambda j: F.struct(F.lit(True).alias("decoy"), decoy(j).alias("token")))
    both = each.select(F.explode(F.concat(F.array(F.struct(F.lit(False).alias("decoy"), "token")), made)).alias("x")).select("x.*")
    return both.select(_class(F.col("token")).alias("class"), "decoy", p_random(F.col("token")).alias("p"))


def thresholds(trials: DataFrame, fdr: float) -> dict[int, float]:
    """Per length class, the p-value from which on tokens are secrets. ``trials``: (class, decoy, p)."""
    bin_ = F.least(F.floor(F.col("p") * BINS), F.lit(BINS - 1)).cast("int").alias("bin")
    binned = trials.where("p is not null").groupBy("class", bin_).agg(F.count_if(~F.col("decoy")).alias("tokens"), F.count_if("decoy").alias("decoys"))
    by: dict[int, dict[int, tuple[int, int]]] = {}
    for r in binned.collect():  # at most BINS rows a class
        by.setdefault(r["class"], {})[r["bin"]] = (r["tokens"], r["decoys"])
    out = {}
    for k, counts in by.items():
        tokens = decoys = 0
        for b in sorted(counts, reverse=True):
            tokens, decoys = tokens + counts[b][0], decoys + counts[b][1]
            if decoys <= fdr * DECOYS * tokens:
                out[k] = b / BINS
    return out


def scan(docs: DataFrame, fdr: float = 0.05, into: str = "secrets") -> DataFrame:
    """The columns of ``docs`` and struct ``into``: array ``spans`` of (start, kind, end), kind an index of KINDS."""
    need(docs, "text")
    text = text_of()
    none = F.array().cast(_SPAN)
    hits = F.when(
        text.rlike(ANY),
        F.concat(_spans(text, ASSIGN, 0, 2, LEAST_VALUE), F.when(text.contains("AKIA"), _spans(text, ACCESS, 1)).otherwise(none), _spans(text, HEX, 2)),
    ).otherwise(none)
    tokens = F.coalesce(_tokens(text), none)
    limit = thresholds(_trials(docs.select(text.alias("text"))), fdr)
    bounds = F.array(*[F.lit(float(limit.get(k, 2.0))) for k in range(len(CLASSES))])

    def chosen(base: Column, more: Column) -> Column:
        random = F.filter(more, lambda y: ~F.exists(base, lambda b: (b.start < y.end) & (y.start < b.end)) & F.coalesce(p_random(y.token) >= F.get(bounds, _class(y.token)), F.lit(False)))
        outer = _let(random, lambda r: F.filter(r, lambda y: ~F.exists(r, lambda z: (z.start <= y.start) & (y.end <= z.end) & (z.end - z.start > y.end - y.start))))
        return F.transform(F.array_sort(F.concat(base, outer)), lambda y: F.struct(y.start.alias("start"), y.kind.alias("kind"), y.end.alias("end")))

    both = F.struct(hits.alias("base"), tokens.alias("more"))
    return docs.withColumn(into, F.struct(_let(both, lambda x: F.when((F.size(x.base) > 0) | (F.size(x.more) > 0), chosen(x.base, x.more)).otherwise(F.array().cast("array<struct<start: int, kind: int, end: int>>"))).alias("spans")))


def written(spans: Column) -> Column:
    """``kind:start:end`` of each span, comma-joined."""
    names = F.array(*[F.lit(k) for k in KINDS])
    return F.array_join(F.transform(spans, lambda s: F.concat_ws(":", F.get(names, s.kind), s.start.cast("string"), s.end.cast("string"))), ",")
