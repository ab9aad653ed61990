"""Language and script identification over hashed character n-grams.

Counting model: one pass over (label, word) counts; each distinct word is expanded into n-grams once. Scores are naive Bayes
sums over observed (bucket, label) pairs; what was never seen is a term of the label alone. Two strategies of prediction give
the same numbers: joins (any size of model, checked against SQL) and an Arrow pass with the model as a file of dense rows.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from corpusforge.functions import labels as lab
from corpusforge.functions.features import BUCKETS, bucket, ngrams_of_word
from corpusforge.functions.scripts import OTHER, PATTERNS, count_letters, main_or_other
from corpusforge.functions.text import LETTERS, words

ALPHA = 0.5


@dataclass
class LidModel:
    """Counts (b, label, c), totals (label, total) with the number of labels, and how features are made."""

    counts: DataFrame
    totals: DataFrame
    buckets: int = BUCKETS
    alpha: float = ALPHA
    pattern: str = LETTERS

    def save(self, path: str) -> None:
        self.counts.write.mode("overwrite").parquet(f"{path}/counts")
        self.totals.write.mode("overwrite").parquet(f"{path}/totals")

    @staticmethod
    def load(spark, path: str, **settings) -> LidModel:
        return LidModel(spark.read.parquet(f"{path}/counts"), spark.read.parquet(f"{path}/totals"), **settings)


def word_counts(rows: DataFrame, keys: list[str], text: str, pattern: str = LETTERS) -> DataFrame:
    """(keys, word, n): the words of each unit, with map-side sums."""
    return rows.select(*keys, F.explode(words(text, pattern)).alias("word")).groupBy(*keys, "word").agg(F.count(F.lit(1)).alias("n"))


def word_buckets(vocabulary: DataFrame, buckets: int = BUCKETS, nmin: int = 2, nmax: int = 5) -> DataFrame:
    """(word, b, tf) of distinct words."""
    grams = vocabulary.select("word", F.explode(ngrams_of_word("word", nmin, nmax)).alias("g"))
    return grams.groupBy("word", bucket("g", buckets).alias("b")).agg(F.count(F.lit(1)).alias("tf"))


def fit_counts(rows: DataFrame, text: str = "line", buckets: int = BUCKETS, alpha: float = ALPHA, pattern: str = LETTERS) -> LidModel:
    """Occurrences of buckets under labels: words are counted before they are cut, n-grams before they are hashed."""
    counted = word_counts(rows, ["label"], text, pattern)
    grams = counted.select("label", "n", F.explode(ngrams_of_word("word")).alias("g")).groupBy("label", "g").agg(F.sum("n").alias("n"))
    counts = grams.groupBy(bucket("g", buckets).alias("b"), "label").agg(F.sum("n").alias("c"))
    return LidModel(counts, counts.groupBy("label").agg(F.sum("c").alias("total")), buckets, alpha, pattern)


def base_weight(model: LidModel) -> Column:
    """The weight of an n-gram that a label never had."""
    return F.log(F.lit(model.alpha) / (F.col("total") + model.alpha * model.buckets))


def scores(units: DataFrame, model: LidModel, keys: list[str], text: str) -> DataFrame:
    """(keys, label, score, grams) for every unit with a word and every label."""
    own = word_counts(units, keys, text, model.pattern)
    spread = word_buckets(own.select("word").distinct(), model.buckets)
    sizes = spread.groupBy("word").agg(F.sum("tf").alias("size"))
    gains = spread.join(model.counts, "b").groupBy("word", "label").agg(F.sum(F.col("tf") * F.log(1 + F.col("c") / model.alpha)).alias("gain"))
    total = own.join(sizes, "word").groupBy(*keys).agg(F.sum(F.col("n") * F.col("size")).alias("grams"))
    gained = own.join(gains, "word").groupBy(*keys, "label").agg(F.sum(F.col("n") * F.col("gain")).alias("gain"))
    every = total.join(F.broadcast(model.totals.select("label", base_weight(model).alias("w0"))))  # a row for each label: a model has a few thousand at most
    return every.join(gained, [*keys, "label"], "left").select(*keys, "label", "grams", (F.coalesce("gain", F.lit(0.0)) + F.col("grams") * F.col("w0")).alias("score"))


def probabilities(scored: DataFrame, keys: list[str], tau: float = 1.0) -> DataFrame:
    """Scores with ``prob``: a softmax, tempered by the root of the text's length in n-grams."""
    over = Window.partitionBy(*keys)
    z = (F.col("score") - F.max("score").over(over)) / (tau * F.sqrt("grams"))
    return scored.withColumn("e", F.exp(z)).withColumn("prob", F.col("e") / F.sum("e").over(over)).drop("e")


def best(scored: DataFrame, keys: list[str], label: str = "pred") -> DataFrame:
    """(keys, pred, prob): the most probable label; of equals (to 9 digits) the first by name."""
    top = F.min(F.struct((-F.round("prob", 9)).alias("p"), "label", "prob")).alias("t")
    return scored.groupBy(*keys).agg(top).select(*keys, F.col("t.label").alias(label), F.col("t.prob").alias("prob"))


def predict(units: DataFrame, model: LidModel, keys: list[str], text: str, tau: float = 1.0, only: list[str] | None = None) -> DataFrame:
    """(keys, pred, prob) of units with at least one word; ``only`` leaves labels out before the best is taken."""
    scored = scores(units, model, keys, text)
    if only is not None:
        scored = scored.filter(F.col("label").isin(*only))
    return best(probabilities(scored, keys, tau), keys)


def predict_restricted(units: DataFrame, model: LidModel, keys: list[str], text: str, tau: float = 1.0) -> DataFrame:
    """As :func:`predict`, but only labels of the text's main script may win; a text without letters may be anything.

    Scripts that are not counted apart are one: a text mostly of their letters can only take a label of such a script.
    """
    main = count_letters(units.select(*keys, text), text).select(*keys, main_or_other(F.col("letters")).alias("main"))
    script = lab.parse("label")["script"]
    composite = F.create_map(*[x for k, v in lab.COMPOSITE.items() for x in (F.lit(k), F.array(*[F.lit(s) for s in v]))])
    fits = F.when(F.col("main") == OTHER, ~script.isin(*PATTERNS, *lab.COMPOSITE)).otherwise((script == F.col("main")) | F.coalesce(F.array_contains(F.element_at(composite, script), F.col("main")), F.lit(False)))
    allowed = scores(units, model, keys, text).join(main, keys).filter(F.col("main").isNull() | fits).drop("main")
    return best(probabilities(allowed, keys, tau), keys)


def reject(pred: DataFrame, min_prob: float) -> DataFrame:
    """Predictions below a probability become misses."""
    return pred.withColumn("pred", F.when(F.col("prob") >= min_prob, F.col("pred")))


def subset_softmax(scored: DataFrame, keys: list[str], labels: list[str], tau: float = 1.0) -> DataFrame:
    """Probabilities among some labels alone."""
    return probabilities(scored.filter(F.col("label").isin(*labels)), keys, tau)


# ------------------------------------------------------------------------------------------------ measures of hashing


def vocabulary(rows: DataFrame, text: str = "line", pattern: str = LETTERS) -> DataFrame:
    """(g, n): distinct n-grams with their number of occurrences."""
    counted = word_counts(rows, [], text, pattern)
    return counted.select("n", F.explode(ngrams_of_word("word")).alias("g")).groupBy("g").agg(F.sum("n").alias("n"))


def collision_report(grams: DataFrame, buckets: int) -> DataFrame:
    """(buckets, n_distinct, occupied, colliding, rate): how many n-grams share a bucket with another."""
    load = grams.groupBy(bucket("g", buckets).alias("b")).agg(F.count(F.lit(1)).alias("k"))
    total = load.agg(F.sum("k").alias("n_distinct"), F.count(F.lit(1)).alias("occupied"), F.sum(F.when(F.col("k") > 1, F.col("k")).otherwise(0)).alias("colliding"))
    return total.select(F.lit(buckets).cast("long").alias("buckets"), "n_distinct", "occupied", "colliding", F.round(F.col("colliding") / F.col("n_distinct"), 6).alias("rate"))


def oov_report(train: DataFrame, test: DataFrame, buckets: int) -> DataFrame:
    """Share of test n-grams that training never had, and of these the share that fall on a bucket of another n-gram."""
    seen = train.select("g", F.lit(True).alias("seen"))
    used = train.select(bucket("g", buckets).alias("b")).distinct().withColumn("used", F.lit(True))
    rows = test.withColumn("b", bucket("g", buckets)).join(seen, "g", "left").join(used, "b", "left")
    total = rows.agg(F.count(F.lit(1)).alias("n_test"), F.count(F.when(F.col("seen").isNull(), 1)).alias("unseen"), F.count(F.when(F.col("seen").isNull() & F.col("used"), 1)).alias("colliding"))
    return total.select("n_test", "unseen", "colliding", F.round(F.col("unseen") / F.col("n_test"), 6).alias("unseen_share"))


def exact_vocab(grams: DataFrame, min_count: int) -> DataFrame:
    """n-grams worth an id of their own."""
    return grams.filter(F.col("n") >= min_count)
