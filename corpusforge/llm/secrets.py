"""Secret scans with DataFrame functions only: fixed patterns, and a battery of randomness tests.

Patterns give the base spans. Besides, every token of 20 characters or more that mixes letters and digits gets an inferred
encoding (hexadecimal or alphanumeric of one case, base 32, base 64 for the rest) and is tested twice.

* Are its symbols random? A chi-squared statistic of uniformity over that alphabet, the runs above and below its middle and
  the correlation of neighbours; a token whose smallest p-value (times three) is under ``LOST`` is ordinary. So at most that
  share of random tokens is lost. The tail of chi-squared is that of a gamma distribution with the statistic's exact mean,
  variance and skewness, which holds for short tokens too.
* Are its symbols ordinary? Under that null hypothesis they repeat at least as often as letters of ordinary text do
  (``REPEATS``), which makes the statistic large; a small one is evidence against it, the stronger the longer the token.

A token is a secret (a span of kind ``random``) if it passes the first and a Benjamini-Hochberg control rejects the second,
in each class of lengths on its own, at a level that is stricter on short tokens. So the control bounds the share of false
secrets among those named. Tokens that a base span overlaps are tested but not named again.

The control needs the distribution of p-values over the corpus: counts by length class and logarithmic bin, some hundred
rows whatever the input. Spans are found by splitting at marks put around matches, so positions are code points.

Defined results: a null or empty text has no spans; repeated rows are reported as often as they occur; a null doc_id stays
null; an empty table gives no rows; other columns are ignored. Texts are changed by redaction only where a span lies.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from corpusforge.engine import written
from corpusforge.functions.text import bound

#: Patterns of the base kinds and the characters that a match has at least (of group 2, or in all).
ASSIGN = r"""((?i)(?:password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?)([A-Za-z0-9+/_.=-]+)"""
ACCESS = r"AKIA[A-Z0-9]+"
HEX = r"[0-9a-f]+"
BASE = (("assign", ASSIGN, 2, 6), ("access", ACCESS, 0, 20), ("hex", HEX, 0, 24))
TOKEN = r"[A-Za-z0-9+/_-]{20,}={0,2}"

ALPHABETS = {
    "hex": "0123456789abcdef",
    "upper hex": "0123456789ABCDEF",
    "base32": "ABCDEFGHIJKLMNOPQRSTUVWXYZ234567",
    "base36": "0123456789abcdefghijklmnopqrstuvwxyz",
    "upper base36": "0123456789ABCDEFGHIJKLMNOPQRSTUVWXYZ",
    "base64": "ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789+/",
}
#: Length classes by their lower ends, and in each the share of false secrets among those named.
LENGTHS = ((20, 0.02), (32, 0.05), (48, 0.1), (80, 0.1))
#: Share of random tokens that the battery may turn away.
LOST = 1e-3
#: Chance that two symbols of ordinary text are equal, by encoding: about that of letters in European languages, less where digits and case mix in.
REPEATS = {"hex": 0.16, "upper hex": 0.16, "base32": 0.065, "base36": 0.06, "upper base36": 0.06, "base64": 0.055}
#: Bins of -log10 p: their width, and how many.
BIN, BINS = 0.05, 400
MARK, OTHER = "\u0001", "\u0003"
#: Pieces of a text that one step of the position count takes.
CHUNK = 256
SPAN = "array<struct<start:int,end:int,value:string>>"


def _pieces(text: Column, pattern: str) -> Column:
    """Gap, match, gap, match, ..., gap."""
    return F.split(F.regexp_replace(F.translate(text, MARK, OTHER), pattern, f"{MARK}$0{MARK}"), MARK)


def spans(text: Column, pattern: str, quick: str | None = None) -> Column:
    """Start, end (code points, end exclusive) and text of the leftmost non-overlapping matches.

    Positions are added up chunk by chunk, so that a text with very many matches takes time in proportion to them.
    """
    pieces = _pieces(text, pattern)
    found = F.transform(
        F.array(pieces),
        lambda p: F.transform(F.sequence(F.lit(0), F.floor((F.size(p) - 1) / CHUNK).cast("int")), lambda c: F.slice(p, c * CHUNK + 1, CHUNK)),
    )[0]
    placed = F.transform(
        F.array(found),
        lambda cs: F.aggregate(
            F.transform(cs, lambda c: F.struct(c.alias("c"), F.aggregate(c, F.lit(0), lambda a, x: a + F.length(x)).alias("n"))),
            F.struct(F.lit(0).alias("at"), F.expr("cast(array() as array<struct<c:array<string>,at:int>>)").alias("out")),
            lambda a, x: F.struct((a["at"] + x["n"]).alias("at"), F.array_append(a["out"], F.struct(x["c"].alias("c"), a["at"].alias("at"))).alias("out")),
            lambda a: a["out"],
        ),
    )[0]
    each = F.transform(
        placed,
        lambda x: F.aggregate(
            x["c"],
            F.struct(x["at"].alias("at"), F.lit(0).alias("k"), F.expr(f"cast(array() as {SPAN})").alias("out")),
            lambda a, s: F.struct(
                (a["at"] + F.length(s)).alias("at"),
                (a["k"] + 1).alias("k"),
                F.when(a["k"] % 2 == 1, F.array_append(a["out"], F.struct(a["at"].alias("start"), (a["at"] + F.length(s)).alias("end"), s.alias("value")))).otherwise(a["out"]).alias("out"),
            ),
            lambda a: a["out"],
        ),
    )
    return F.when(F.coalesce(text.rlike(quick or pattern), F.lit(False)), F.flatten(each)).otherwise(F.expr(f"cast(array() as {SPAN})"))


def _long_enough(pattern: str, group: int, least: int):
    return lambda value: F.length(F.regexp_extract(value, pattern, group) if group else value) >= least


def _kept(found: Column, passes, number: int) -> Column:
    return F.transform(F.filter(found, lambda s: passes(s["value"])), lambda s: F.struct(s["start"].alias("start"), F.lit(number).alias("kind"), s["end"].alias("end")))


def _count(number: int) -> Column:
    return F.size(F.filter("base", lambda s: s["kind"] == number)).cast("long")


#: A quick pattern that every passing match contains, so that most texts need no splitting.
QUICK = {"assign": ASSIGN, "access": r"AKIA[A-Z0-9]{16}", "hex": r"[0-9a-f]{24}"}


def base_spans(text: Column) -> Column:
    """Spans of the three fixed kinds: (start, kind number, end), sorted."""
    kinds = []
    for number, (kind, pattern, group, least) in enumerate(BASE):
        kinds.append(_kept(spans(text, pattern, QUICK[kind]), _long_enough(pattern, group, least), number))
    return F.array_sort(F.concat(*kinds))


def _tail(z: Column) -> Column:
    """Upper tail of the normal distribution, by the usual rational approximation."""

    def above(x: Column) -> Column:
        t = 1 / (1 + 0.2316419 * x)
        return F.exp(-x * x / 2) / 2.5066282746310002 * t * (0.319381530 + t * (-0.356563782 + t * (1.781477937 + t * (-1.821255978 + t * 1.330274429))))

    return bound(z, lambda x: F.when(x >= 0, above(x)).otherwise(1 - above(-x)))


def _chi_tail(chi: Column, n: Column, k: Column) -> Column:
    """Upper tail of the uniformity statistic of n symbols in k cells: a gamma distribution of its first three moments."""
    spread = F.sqrt(2 * (k - 1) * (n - 1) / n)
    root = 2 * spread * spread * spread / (4 * (k - 1) * (n - 1) * (2 * n + k - 6) / (n * n))  # the root of the gamma's shape
    z = 3 * root * (F.cbrt(F.greatest(1 + (chi - (k - 1)) / spread / root, F.lit(0.0))) - 1 + 1 / (9 * root * root))
    return _tail(z)


def _symbols(v: Column) -> Column:
    """What is tested: without separators where letters have one case and 20 characters are left, else as base 64."""
    bare = F.regexp_replace(v, "[-_/+=]", "")
    one_case = ~(v.rlike("[a-z]") & v.rlike("[A-Z]"))
    return F.when(one_case & (F.length(bare) >= LENGTHS[0][0]), bare).otherwise(F.translate(F.regexp_replace(v, "=+$", ""), "-_", "+/"))


def _encoding(v: Column) -> Column:
    digit, letter, s = v.rlike("[0-9]"), v.rlike("[A-Za-z]"), _symbols(v)
    return (
        F.when(~(digit & letter), F.lit(None))
        .when(s.rlike("^[0-9a-f]+$"), F.lit("hex"))
        .when(s.rlike("^[0-9A-F]+$"), F.lit("upper hex"))
        .when(s.rlike("^[A-Z2-7]+$"), F.lit("base32"))
        .when(s.rlike("^[0-9a-z]+$"), F.lit("base36"))
        .when(s.rlike("^[0-9A-Z]+$"), F.lit("upper base36"))
        .otherwise(F.lit("base64"))
    )


def _map(values: dict) -> Column:
    return F.create_map(*[F.lit(x) for pair in values.items() for x in pair])


def p_values(value: Column, encoding: Column) -> Column:
    """(random, ordinary): p-values of the two hypotheses on a token's symbols."""

    def tests(x: Column) -> Column:
        s, a = x["s"], x["a"]
        n, k = F.length(s).cast("double"), F.length(a).cast("double")
        counts = F.transform(F.split(a, ""), lambda c: F.length(s) - F.length(F.replace(s, c)))
        chi = F.aggregate(counts, F.lit(0.0), lambda t, c: t + c * c) * k / n - n
        symbols = F.transform(F.split(s, ""), lambda c: F.instr(a, c).cast("double") - 0.5 - k / 2)
        return bound(F.struct(n.alias("n"), k.alias("k"), chi.alias("chi"), symbols.alias("symbols"), x["repeats"].alias("repeats")), graded)

    def graded(x: Column) -> Column:
        n, k, symbols = x["n"], x["k"], x["symbols"]
        pairs = F.zip_with(F.slice(symbols, F.lit(1), F.size(symbols) - 1), F.slice(symbols, F.lit(2), F.size(symbols) - 1), lambda p, q: F.struct(p.alias("p"), q.alias("q")))
        high = F.size(F.filter(symbols, lambda y: y > 0)).cast("double")
        low = n - high
        runs = 1.0 + F.size(F.filter(pairs, lambda y: (y["p"] > 0) != (y["q"] > 0)))
        mean = 2 * high * low / n + 1
        z_runs = F.abs(runs - mean) / F.sqrt(F.greatest((mean - 1) * (mean - 2) / (n - 1), F.lit(1e-9)))
        middle = F.aggregate(symbols, F.lit(0.0), lambda t, y: t + y) / n
        z_serial = bound(middle, lambda m: F.abs(_together(pairs, m) / F.greatest(F.aggregate(symbols, F.lit(0.0), lambda t, y: t + (y - m) * (y - m)), F.lit(1e-9)) + 1 / n) * F.sqrt(n))
        random = F.least(F.lit(1.0), 3 * F.least(_chi_tail(x["chi"], n, k), 2 * _tail(z_runs), 2 * _tail(z_serial)))
        excess = (n - 1) * (k * x["repeats"] - 1)
        ordinary = 1 - _tail((x["chi"] - (k - 1) - excess) / F.sqrt(2 * (k - 1) + 4 * excess))
        return F.struct(random.alias("random"), ordinary.alias("ordinary"))

    return bound(F.struct(_symbols(value).alias("s"), F.element_at(_map(ALPHABETS), encoding).alias("a"), F.element_at(_map(REPEATS), encoding).alias("repeats")), tests)


def _together(pairs: Column, middle: Column) -> Column:
    return F.aggregate(pairs, F.lit(0.0), lambda t, y: t + (y["p"] - middle) * (y["q"] - middle))


def candidates(text: Column) -> Column:
    """Tokens under test: (start, end, class of length, bin of the p-value against ordinary text; bin 0 if not random)."""
    mixed = F.filter(spans(text, TOKEN), lambda s: _encoding(s["value"]).isNotNull())

    def graded(s: Column) -> Column:
        n, kind = s["end"] - s["start"], F.lit(0)
        for number, (least, _) in enumerate(LENGTHS):
            kind = F.when(n >= least, F.lit(number)).otherwise(kind)
        p = bound(p_values(s["value"], _encoding(s["value"])), lambda x: F.when(x["random"] < LOST, F.lit(1.0)).otherwise(F.least(F.greatest(x["ordinary"], F.lit(1e-30)), F.lit(1.0))))
        return F.struct(s["start"].alias("start"), s["end"].alias("end"), kind.alias("class"), F.least(F.floor(-F.log10(p) / BIN), F.lit(BINS)).cast("int").alias("bin"))

    return F.transform(mixed, graded)


def rejected_from(tested: DataFrame) -> dict[int, int]:
    """For each class of lengths the bin from which on tokens are no ordinary text; ``tested`` has ``candidates`` arrays.

    Bins stand for their upper end, so the control is never laxer than on the values themselves.
    """
    bins = tested.select(F.explode("candidates").alias("c")).groupBy(F.col("c.class").alias("class"), F.col("c.bin").alias("bin")).agg(F.count(F.lit(1)).alias("n"))
    found: dict[int, int] = {}
    counts: dict[int, dict[int, int]] = {}
    for r in bins.collect():  # at most len(LENGTHS) * (BINS + 1) rows
        counts.setdefault(r["class"], {})[r["bin"]] = r["n"]
    for number, (_, level) in enumerate(LENGTHS):
        own = counts.get(number, {})
        total, seen, found[number] = sum(own.values()), 0, BINS + 1
        for b in sorted(own, reverse=True):
            seen += own[b]
            if 10 ** (-b * BIN) * total <= level * seen:
                found[number] = b
    return found


def _accepted(limits: dict[int, int], c: Column) -> Column:
    return c["bin"] >= F.element_at(_map(limits), c["class"])


def _named(base: Column, tested: Column, limits: dict[int, int]) -> Column:
    """Spans of kind ``random``: secrets by the tests that no base span overlaps."""
    free = lambda c: ~F.exists(base, lambda b: (b["start"] < c["end"]) & (c["start"] < b["end"]))
    return F.transform(F.filter(tested, lambda c: _accepted(limits, c) & free(c)), lambda c: F.struct(c["start"].alias("start"), F.lit(len(BASE)).alias("kind"), c["end"].alias("end")))


def scan(docs: DataFrame) -> DataFrame:
    """(doc_id, base, random): sorted base spans and accepted spans of the tests, for every document."""
    text = F.col("text")
    tested = docs.select(F.col("doc_id").cast("long"), F.col("text").cast("string"))
    tested = written(tested.select("doc_id", base_spans(text).alias("base"), candidates(text).alias("candidates")), "tested")
    limits = rejected_from(tested)
    return tested.select("doc_id", "base", _named(F.col("base"), F.col("candidates"), limits).alias("random"))


def _listed(spans: Column) -> Column:
    names = F.array(*[F.lit(kind) for kind, *_ in BASE], F.lit("random"))
    return F.array_join(F.transform(spans, lambda s: F.concat_ws(":", F.element_at(names, s["kind"] + 1), s["start"], s["end"])), ",")


def report(scanned: DataFrame) -> DataFrame:
    """Counts by kind, a digest of the base spans, and all spans as text."""
    counts = [_count(number).alias(f"n_{kind}") for number, (kind, *_) in enumerate(BASE)]
    return scanned.select("doc_id", *counts, F.sha2(_listed(F.col("base")), 256).alias("base_sha256"), _listed(F.array_sort(F.concat("base", "random"))).alias("spans"))


PUT = "[SECRET]"
#: Code points of a text that are cut at once.
CUT = 4096


def _without(text: Column, found: Column) -> Column:
    """The text with ``PUT`` for every stretch that spans cover: cut chunk by chunk, in time in proportion to the text.

    A chunk takes the spans that reach into it, moved to its own positions; one that began in an earlier chunk has left
    its placeholder there.
    """

    def rewritten(chunk: Column, number: Column) -> Column:
        first = number * CUT
        own = F.filter(found, lambda s: (s["end"] > first) & (s["start"] < first + CUT))
        step = lambda a, s: F.struct(
            F.greatest(a["at"], s["end"] - first).alias("at"),
            F.concat(
                a["out"],
                F.when(s["start"] - first > a["at"], F.substring(chunk, a["at"] + 1, s["start"] - first - a["at"])).otherwise(F.lit("")),
                F.when(s["start"] - first >= a["at"], F.lit(PUT)).otherwise(F.lit("")),
            ).alias("out"),
        )
        cut = F.aggregate(own, F.struct(F.lit(0).alias("at"), F.lit("").alias("out")), step, lambda a: F.concat(a["out"], F.substring(chunk, a["at"] + 1, F.lit(CUT))))
        return F.when(F.size(own) > 0, cut).otherwise(chunk)

    return F.array_join(F.transform(F.regexp_extract_all(text, F.lit(f"(?s).{{1,{CUT}}}"), 0), rewritten), "")


def redact(docs: DataFrame) -> DataFrame:
    """Documents with a placeholder for what :func:`scan` finds; ``n_chars`` follows the text, other columns stay.

    The tests' limits are taken from the documents themselves, then each text is rewritten where it lies, without a join.
    """
    text = F.col("text").cast("string")
    limits = rejected_from(docs.select(candidates(text).alias("candidates")).filter(F.size("candidates") > 0))
    every = bound(base_spans(text), lambda base: F.array_sort(F.concat(base, _named(base, candidates(text), limits))))
    out = docs.withColumn("text", bound(every, lambda found: F.when(F.size(found) > 0, _without(text, found)).otherwise(text)))
    return out.withColumn("n_chars", F.length("text").cast("long")) if "n_chars" in docs.columns else out
