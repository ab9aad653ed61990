"""Labelled lines for training: union, script filter, decontamination, deduplication, split and caps."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from corpusforge.functions import labels as lab
from corpusforge.functions.scripts import PATTERNS, letters_in
from corpusforge.functions.text import bound, bucket_of, exploded_lines, share, words

#: Words of the benchmark that may be broadcast; a larger benchmark is joined by shuffle.
BROADCAST_WORDS = 2_000_000


def labelled_lines(docs: DataFrame) -> DataFrame:
    """(doc_id, source, pos, line, label, part): lines with their document's label and its tenth of the corpus.

    The tenth comes from a hash of the text, so copies of a document lie on one side of every split.
    """
    own = docs.select("doc_id", "source", "text", lab.label_of("lang").alias("label"), bucket_of(F.col("text"), 10).alias("part"))
    return exploded_lines(own)


def union_sources(*sources: DataFrame) -> DataFrame:
    return reduce(lambda a, b: a.unionByName(b, allowMissingColumns=True), sources)


def admissible_share(line: Column, iso: Column) -> Column:
    """Share of the letters of a line whose script the language is written in."""
    good = F.lit(0)
    for script in PATTERNS:
        able = [k for k, v in lab.ADMISSIBLE.items() if script in v]
        if able:
            good = good + F.when(iso.isin(*able), letters_in(line, script)).otherwise(0)
    return share(good, F.regexp_count(line, F.lit(r"\p{L}")))


def script_filter(lines: DataFrame, min_share: float = 0.5) -> DataFrame:
    """Lines with enough letters of a script that is admissible for their label."""
    return lines.filter(admissible_share(F.col("line"), lab.parse("label")["iso"]) >= min_share)


def split_name(part: Column | str = "part", shares: tuple[float, float, float] = (0.8, 0.1, 0.1)) -> Column:
    part = F.col(part) if isinstance(part, str) else part
    return F.when(part < round(10 * shares[0]), "train").when(part < round(10 * (shares[0] + shares[1])), "valid").otherwise("test")


def dedup_exact(lines: DataFrame, key: str = "line") -> DataFrame:
    """The first line (by doc_id and pos) of those that are equal but for case and blanks; only hashes are grouped."""
    same = F.md5(F.trim(F.regexp_replace(F.lower(key), r"\s+", " ")))
    first = lines.groupBy(same.alias("same")).agg(F.min(F.struct("doc_id", "pos")).alias("first"), F.count(F.lit(1)).alias("copies"))
    return first.select("first.doc_id", "first.pos", "copies")


def resample(lines: DataFrame, cap: int, key: str = "label") -> DataFrame:
    """At most ``cap`` lines of each label, by hash of their place; the same whatever the layout.

    Lines that can't be among them are dropped before the shuffle: their hash lies beyond a generous multiple of the cap.
    """
    order = F.md5(F.concat_ws(":", "doc_id", "pos"))
    sizes = lines.groupBy(key).agg(F.count(F.lit(1)).alias("n"))
    small = lines.withColumn("order", order).join(F.broadcast(sizes), key)
    reach = F.conv(F.substring("order", 1, 8), 16, 10).cast("double") / float(1 << 32)
    likely = small.filter((F.col("n") <= 4 * cap) | (reach <= (4.0 * cap + 200) / F.col("n")))
    rank = F.row_number().over(Window.partitionBy(key).orderBy("order", "doc_id", "pos"))
    return likely.withColumn("rank", rank).filter(F.col("rank") <= cap).drop("order", "n")


def resample_by_temperature(lines: DataFrame, size: int, alpha: float = 0.5, key: str = "label") -> DataFrame:
    """Lines of each label at the rate that brings its share near n**alpha, n being its lines, and ``size`` lines in all.

    A label of fewer lines than its share asks for keeps all of them, so a sample may be smaller. Sizes are expected, not exact:
    a line is taken or left by the hash of its place alone, the same whatever the layout, and lines are not shuffled.
    """
    sizes = lines.groupBy(key).agg(F.count(F.lit(1)).alias("n")).withColumn("mass", F.pow(F.col("n").cast("double"), F.lit(alpha)))
    rates = sizes.withColumn("rate", F.least(F.lit(1.0), size * F.col("mass") / F.sum("mass").over(Window.partitionBy()) / F.col("n"))).select(key, "rate")  # a row a label
    place = F.conv(F.substring(F.md5(F.concat_ws(":", F.lit("temperature"), "doc_id", "pos")), 1, 8), 16, 10).cast("double") / float(1 << 32)
    return lines.join(F.broadcast(rates), key).filter(place < F.col("rate"))


def grams(text: Column, n: int = 4) -> Column:
    """Distinct word n-grams of a text."""
    none = F.expr("cast(array() as array<string>)")
    at = lambda w, i: F.concat_ws(" ", *[F.get(w, i + k) for k in range(n)])
    of = lambda w: F.when(F.size(w) >= n, F.transform(F.sequence(F.lit(0), F.size(w) - n), lambda i: at(w, i))).otherwise(none)
    return F.array_distinct(bound(words(text), of))


def bench_sentences(bench: DataFrame) -> DataFrame:
    """(item_id, sent, sentence) of the benchmark: its lines cut at full stops."""
    cut = bench.select("item_id", F.posexplode(F.split("text", r"[.\n]")).alias("sent", "sentence"))
    return cut.withColumn("sentence", F.trim("sentence")).filter("sentence <> ''")


def contained(units: DataFrame, bench: DataFrame, ids: list[str], text: str, n: int = 4, min_share: float = 1.0) -> DataFrame:
    """(ids, item_id, sent): units that hold the n-grams of a benchmark sentence, all or the given share.

    Sentences of fewer than n words have no n-gram and never match. The benchmark's grams are broadcast while they are few.
    """
    wanted = bench.select("item_id", "sent", F.explode(grams(F.col("sentence"), n)).alias("gram"))
    need = wanted.groupBy("item_id", "sent").agg(F.count(F.lit(1)).alias("need"))
    wanted = wanted.join(need, ["item_id", "sent"])
    few = bench.agg(F.sum(F.size(words("sentence")))).first()[0] or 0
    held = units.select(*ids, F.explode(grams(F.col(text), n)).alias("gram"))
    hits = held.join(F.broadcast(wanted) if few <= BROADCAST_WORDS else wanted, "gram")
    found = hits.groupBy(*ids, "item_id", "sent").agg(F.count(F.lit(1)).alias("found"), F.first("need").alias("need"))
    return found.filter(F.col("found") >= min_share * F.col("need")).select(*ids, "item_id", "sent")


def decontaminate(lines: DataFrame, bench: DataFrame, n: int = 4) -> DataFrame:
    """Lines that hold no benchmark sentence."""
    return lines.join(contained(lines, bench_sentences(bench), ["doc_id", "pos"], "line", n), ["doc_id", "pos"], "left_anti")
