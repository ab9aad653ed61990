"""Queries of the reference methods over the given tables, one for each method, variant, baseline, measure and workload."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, Observation, SparkSession
from pyspark.sql import functions as F

from corpusforge.engine import read
from corpusforge.functions import cost, features, html, lsh, pii, scripts
from corpusforge.functions import labels as lab
from corpusforge.functions import warnings as W
from corpusforge.functions.text import exploded_lines, words
from corpusforge.operators import audit, compare, content, coverage, curate, dedup, evaluate, filters, lid, noise, relational, softmax, traindata
from corpusforge.plans import annotate, pipeline
from corpusforge.streaming import stream

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}

#: Lines drawn for each reject label, when training and when testing.
REJECT_TRAIN, REJECT_TEST = 200, 40
BUCKETS = features.BUCKETS


def query(f: Query) -> Query:
    QUERIES[f.__name__] = f
    return f


# ------------------------------------------------------------------------------------------------------- common inputs


def docs(spark, sf, *columns):
    return read(spark, sf, "documents", *(columns or ("doc_id", "text", "lang", "source", "n_chars")))


def lines(spark, sf):
    return traindata.labelled_lines(docs(spark, sf))


def train_lines(spark, sf):
    return lines(spark, sf).filter("part < 8")


def test_docs(spark, sf):
    """Held-out documents with their gold label."""
    part = traindata.bucket_of(F.col("text"), 10)
    return docs(spark, sf).filter(part == 9).select("doc_id", "text", lab.label_of("lang").alias("gold"))


def model(spark, sf, labels: tuple[str, ...] | None = None, buckets: int = BUCKETS) -> lid.LidModel:
    rows = train_lines(spark, sf)
    return lid.fit_counts(rows.filter(F.col("label").isin(*labels)) if labels else rows, buckets=buckets)


#: How many words lines of unseen scripts have, when training and when testing.
REJECT_WORDS = {"train": (5, 15), "test": (4, 9)}


def reject_rows(spark, sf, n, seed):
    """(kind, label, row, line) of unseen scripts and noise; test rows take other seeds, lengths and lines of the corpus."""
    own = lines(spark, sf).filter("part < 8" if seed == "train" else "part = 9")
    return noise.rejects(spark, own, n, seed, words=REJECT_WORDS[seed])


def release(spark, sf, name: str) -> lid.LidModel:
    """Releases differ in their labels: r1 and r2 know languages (r2 asks for the text's script when it predicts), r3 has reject labels."""
    rows = train_lines(spark, sf).select("label", "line")
    if name == "r3":
        rows = rows.union(reject_rows(spark, sf, REJECT_TRAIN, "train").select("label", "line"))
    return lid.fit_counts(rows, pattern=r"\S+" if name == "r3" else r"\p{L}+")


#: What numbers of noise rows begin at, so that they are no document's.
NOISE_ID = 10**12


def noise_docs(spark, sf):
    """(doc_id, text, gold): noise of the test seed as documents; the number tells its kind and row."""
    kinds = [f"und_{s}" for s in noise.unseen_scripts()] + list(noise.KINDS)
    place = F.element_at(F.create_map(*[F.lit(x) for i, k in enumerate(kinds) for x in (k, i)]), F.col("kind"))
    return reject_rows(spark, sf, REJECT_TEST, "test").select((F.lit(NOISE_ID) + place * 1_000_000 + F.col("row")).alias("doc_id"), F.col("line").alias("text"), F.col("label").alias("gold"))


def mixed_test(spark, sf):
    """Held-out documents beside noise of another seed: (id, text, gold, is_noise)."""
    true = test_docs(spark, sf).select(F.col("doc_id").alias("id"), "text", "gold", F.lit(False).alias("is_noise"))
    return true.union(noise_docs(spark, sf).select("doc_id", "text", "gold", F.lit(True)))


def mixed_predictions(spark, sf, name):
    by = annotate.Pass(lines=False, restrict=name == "r2")
    return annotate.identify_rows(mixed_test(spark, sf), release(spark, sf, name), by=by).select("id", "gold", "is_noise", "pred", "prob")


def predicted(spark, sf, m=None, only=None):
    """(doc_id, gold, pred, prob) of held-out documents: the Arrow pass, or the join where only some labels may win."""
    test, m = test_docs(spark, sf), m or model(spark, sf)
    if only is None:
        return annotate.identify_rows(test, m, by=annotate.Pass(lines=False)).select("doc_id", "gold", "pred", "prob")
    return test.select("doc_id", "gold").join(lid.predict(test, m, ["doc_id"], "text", only=only), "doc_id", "left")


# --------------------------------------------------------------------------------------------- features, model, scores


@query
def ngram_counts(spark, sf):
    g = lid.vocabulary(lines(spark, sf))
    return g.groupBy(F.length("g").alias("size")).agg(F.count(F.lit(1)).alias("n_distinct"), F.sum("n").alias("n"))


@query
def hash_buckets(spark, sf):
    g = lid.vocabulary(lines(spark, sf))
    return g.select("g", features.bucket("g", BUCKETS).alias("b"), features.fnv1a("g").alias("fnv"))


@query
def collision_rate(spark, sf):
    g = lid.vocabulary(lines(spark, sf))
    out = None
    for buckets in (1 << 12, 1 << 16, 1 << 20, BUCKETS):
        part = lid.collision_report(g, buckets)
        out = part if out is None else out.union(part)
    return out


@query
def oov_share(spark, sf):
    rows = lines(spark, sf)
    return lid.oov_report(lid.vocabulary(rows.filter("part < 8")), lid.vocabulary(rows.filter("part = 9")), BUCKETS)


@query
def exact_vocab(spark, sf):
    return lid.exact_vocab(lid.vocabulary(lines(spark, sf)), 50)


@query
def lid_train_counts(spark, sf):
    m = model(spark, sf)
    return m.counts.groupBy("label").agg(F.count(F.lit(1)).alias("n_buckets"), F.sum("c").alias("total"), F.max("c").alias("largest"))


@query
def lid_predict_docs(spark, sf):
    """By joins alone, as for a model of any size."""
    test = test_docs(spark, sf)
    return test.select("doc_id").join(lid.predict(test, model(spark, sf), ["doc_id"], "text"), "doc_id", "left").select("doc_id", "pred", F.round("prob", 4).alias("prob"))


@query
def lid_predict_lines(spark, sf):
    rows = lines(spark, sf).filter("part = 9").select("doc_id", "pos", "line")
    return lid.predict(rows, model(spark, sf), ["doc_id", "pos"], "line").select("doc_id", "pos", "pred", F.round("prob", 4).alias("prob"))


@query
def lid_predict_fused(spark, sf):
    """The Arrow pass: documents and all their lines at once."""
    out = annotate.identify(test_docs(spark, sf), model(spark, sf))
    return out.select("doc_id", "pred", F.round("prob", 4).alias("prob"), F.size("lines").alias("n_lines"))


@query
def lid_reject_threshold(spark, sf):
    return lid.reject(predicted(spark, sf), 0.9).groupBy(F.col("pred").isNull().alias("miss")).agg(F.count(F.lit(1)).alias("n"))


@query
def lid_script_restricted(spark, sf):
    """Only labels of the text's main script may win."""
    test = test_docs(spark, sf)
    scored = lid.scores(test, model(spark, sf), ["doc_id"], "text")
    main = test.select("doc_id", scripts.main_script("text", ("Latn", "Cyrl", "Arab")).alias("script"))
    allowed = scored.join(main, "doc_id").filter(lab.parse("label")["script"] == F.col("script")).drop("script")
    return lid.best(lid.probabilities(allowed, ["doc_id"]), ["doc_id"]).select("doc_id", "pred")


@query
def lid_subset_softmax(spark, sf):
    scored = lid.scores(test_docs(spark, sf), model(spark, sf), ["doc_id"], "text")
    p = lid.subset_softmax(scored, ["doc_id"], ["eng_Latn", "fra_Latn"])
    return p.select("doc_id", "label", F.round("prob", 4).alias("prob"))


@query
def lid_bench_restricted(spark, sf):
    return predicted(spark, sf, only=["deu_Latn", "eng_Latn", "spa_Latn"]).select("doc_id", "pred")


@query
def lid_confusion(spark, sf):
    return evaluate.confusion(predicted(spark, sf))


def weak(spark, sf):
    """A model with a tiny hash range, which confuses languages."""
    return model(spark, sf, buckets=64)


def weak_lines(spark, sf, m=None):
    rows = lines(spark, sf).filter("part = 9").select("doc_id", "pos", "line", F.col("label").alias("gold"))
    return rows.select("doc_id", "pos", "gold").join(lid.predict(rows, m or weak(spark, sf), ["doc_id", "pos"], "line"), ["doc_id", "pos"], "left")


#: Languages of the given tables and their branches, as macro-languages stand over their members.
FAMILIES = [("eng_Latn", "gmw"), ("deu_Latn", "gmw"), ("fra_Latn", "roa"), ("spa_Latn", "roa")]


@query
def lid_confused_pairs(spark, sf):
    pairs = curate.confused_pairs(evaluate.confusion(weak_lines(spark, sf)))
    return curate.annotate_pairs(pairs, spark.createDataFrame(FAMILIES, "label string, macro_label string")).select("a", "b", "n_ab", "n_ba", "n", "one_macro")


@query
def lid_f1(spark, sf):
    return evaluate.f1(predicted(spark, sf))


@query
def lid_f1_macro(spark, sf):
    p = predicted(spark, sf)
    return evaluate.macro(evaluate.f1(p), "f1").union(evaluate.micro_f1(p))


@query
def lid_fpr(spark, sf):
    return evaluate.fpr(predicted(spark, sf))


@query
def lid_worst_labels(spark, sf):
    return evaluate.worst(evaluate.f1(weak_lines(spark, sf)), 3)


@query
def lid_baseline_compact(spark, sf):
    """The compact baseline: the same method in few buckets."""
    return evaluate.f1(predicted(spark, sf, model(spark, sf, buckets=4096)))


@query
def lid_baseline_narrow(spark, sf):
    """The narrow closed-set baseline with a threshold, whose rest are misses."""
    p = lid.reject(predicted(spark, sf, model(spark, sf, CLOSED)), 0.8)
    return p.groupBy("gold", F.coalesce("pred", F.lit("none")).alias("pred")).agg(F.count(F.lit(1)).alias("n"))


@query
def lid_release_delta(spark, sf):
    """F1 of the three releases on documents and noise; a closed set can't name noise."""
    out = None
    for name in ("r1", "r2", "r3"):
        part = evaluate.f1(mixed_predictions(spark, sf, name)).select("label", F.col("f1").alias(name))
        out = part if out is None else out.join(part, "label", "full")
    return out.select("label", "r1", "r2", "r3", F.round(F.col("r2") - F.col("r1"), 6).alias("r2_gain"), F.round(F.col("r3") - F.col("r1"), 6).alias("r3_gain"))


@query
def lid_release_noise(spark, sf):
    """What each release calls the noise of a kind: a language (wrong), a reject label, or nothing."""
    out = None
    for name in ("r1", "r2", "r3"):
        p = mixed_predictions(spark, sf, name).filter("is_noise")
        said = F.when(F.col("pred").isNull(), "nothing").when(pipeline.is_rejected("pred"), "reject").otherwise("language")
        part = p.groupBy(F.substring("gold", 1, 3).alias("kind"), said.alias("said")).agg(F.count(F.lit(1)).alias("n")).withColumn("release", F.lit(name))
        out = part if out is None else out.union(part)
    return out


@query
def lid_calibration(spark, sf):
    return evaluate.calibration(predicted(spark, sf))


@query
def lid_seed_variance(spark, sf):
    """Spread of F1 over trainings on different nine tenths."""
    out = None
    for seed in range(3):
        m = lid.fit_counts(train_lines(spark, sf).filter(traindata.bucket_of(F.concat_ws(":", F.lit(str(seed)), "doc_id"), 10) > 0))
        part = evaluate.macro(evaluate.f1(predicted(spark, sf, m)), "f1").withColumn("seed", F.lit(seed))
        out = part if out is None else out.union(part)
    return out.agg(F.round(F.avg("value"), 6).alias("mean"), F.round(F.stddev_pop("value"), 6).alias("deviation"))


@query
def lid_softmax_f1(spark, sf):
    """The classifier of averaged embeddings, one epoch."""
    m = softmax.fit_softmax(train_lines(spark, sf))
    test = test_docs(spark, sf)
    return evaluate.f1(test.select("doc_id", "gold").join(softmax.predict_softmax(test, m, "doc_id"), "doc_id"))


@query
def lid_softmax_compact(spark, sf):
    """The compact neural baseline: few buckets, small vectors."""
    m = softmax.fit_softmax(train_lines(spark, sf), buckets=2048, dim=8)
    test = test_docs(spark, sf)
    return evaluate.macro(evaluate.f1(test.select("doc_id", "gold").join(softmax.predict_softmax(test, m, "doc_id"), "doc_id")), "f1")


def benchmarks(spark, sf):
    """(bench, id, text, gold) of three test sets: held-out documents, sampled held-out lines, pages of another domain."""
    lines_ = evaluate.indomain_sample(lines(spark, sf).filter("part = 9"), 50).select(F.lit("lines"), F.col("doc_id") * 100_000 + F.col("pos"), F.col("line"), F.col("label"))
    pages = page_text(spark, sf).select(F.lit("pages"), "page_id", "text", "gold")
    return test_docs(spark, sf).select(F.lit("documents").alias("bench"), F.col("doc_id").alias("id"), "text", "gold").union(lines_).union(pages)


@query
def lid_benchmark_table(spark, sf):
    """(model, bench, f1, fpr): macro averages of three models over three test sets."""
    test, out = benchmarks(spark, sf), None
    for name, m in (("full", model(spark, sf)), ("compact", model(spark, sf, buckets=4096)), ("closed", model(spark, sf, CLOSED))):
        p = annotate.identify_rows(test, m, by=annotate.Pass(lines=False))
        for bench in ("documents", "lines", "pages"):
            part = evaluate.prf(p.filter(F.col("bench") == bench)).agg(F.round(F.avg("f1"), 4).alias("f1"), F.round(F.avg("fpr"), 4).alias("fpr"))
            part = part.select(F.lit(name).alias("model"), F.lit(bench).alias("bench"), "f1", "fpr")
            out = part if out is None else out.union(part)
    return out


@query
def lid_softmax_seeds(spark, sf):
    """Spread of the classifier's F1 over other initial seeds."""
    test, out = test_docs(spark, sf), None
    for seed in range(3):
        m = softmax.fit_softmax(train_lines(spark, sf), buckets=1 << 16, seed=seed)
        part = evaluate.macro(evaluate.f1(test.select("doc_id", "gold").join(softmax.predict_softmax(test, m, "doc_id"), "doc_id")), "f1")
        out = part if out is None else out.union(part)
    return out.agg(F.count(F.lit(1)).alias("seeds"), F.round(F.avg("value"), 6).alias("mean"), F.round(F.stddev_pop("value"), 6).alias("deviation"))


@query
def lid_indomain_sample(spark, sf):
    return evaluate.indomain_sample(lines(spark, sf).filter("part = 9"), 50).select("label", "doc_id", "pos", "rank")


@query
def lid_label_overlap(spark, sf):
    return evaluate.label_overlap(lab.languages(spark), train_lines(spark, sf))


@query
def lid_rejection_vs_threshold(spark, sf):
    """Reject labels against a threshold: noise turned away and true text lost."""
    out = None
    for name, of in (("threshold", "r1"), ("script", "r2"), ("labels", "r3")):
        rule = pipeline.is_rejected("pred") if name != "threshold" else F.coalesce(F.col("prob") < 0.5, F.lit(True))
        part = evaluate.rejection(mixed_predictions(spark, sf, of), rule).withColumn("method", F.lit(name))
        out = part if out is None else out.union(part)
    return out


@query
def lid_cousins(spark, sf):
    return evaluate.cousins(predicted(spark, sf, model(spark, sf, CLOSED)), ["spa_Latn"])


def page_text(spark, sf):
    p = read(spark, sf, "pages", "page_id", "url", "html")
    return p.select("page_id", "url", html.host("url").alias("host"), html.strip_tags("html").alias("text"), lab.label_of(html.html_lang("html")).alias("gold"))


def page_predictions(spark, sf):
    p = page_text(spark, sf)
    return p.select("page_id", "gold").join(annotate.identify(p, model(spark, sf), "page_id", with_lines=False).select("page_id", "pred", "prob"), "page_id")


@query
def lid_domain_gap(spark, sf):
    """Held-out documents against pages, whose text also holds what surrounds the article."""
    return evaluate.domain_gap(evaluate.f1(predicted(spark, sf)), evaluate.f1(page_predictions(spark, sf)))


@query
def lid_conversations(spark, sf):
    """Short turns without gold: how often the turns of a conversation agree."""
    c = read(spark, sf, "conversations", "conv_id", "turn", "text").withColumn("id", F.col("conv_id") * 1000 + F.col("turn"))
    p = c.select("id", "conv_id").join(annotate.identify(c, model(spark, sf), "id", with_lines=False), "id")
    n = p.groupBy("conv_id", "pred").agg(F.count(F.lit(1)).alias("n")).groupBy("conv_id").agg(F.max("n").alias("most"), F.sum("n").alias("n"))
    return n.agg(F.count(F.lit(1)).alias("conversations"), F.round(F.sum("most") / F.sum("n"), 6).alias("consistency"))


# ----------------------------------------------------------------------------------------- labels, scripts, training data


@query
def label_parse(spark, sf):
    rows = docs(spark, sf, "lang").select(lab.label_of("lang").alias("label")).distinct().union(spark.createDataFrame([("und_Mong",), ("zxx-Latn",), ("jpn-Jpan",)], "label string"))
    return rows.select("label", lab.parse("label")["iso"].alias("iso"), lab.parse("label")["script"].alias("script"), lab.parse("label")["kind"].alias("kind"), lab.word_based("label").alias("word_based"))


#: Letters and what they become when a text is moved to another script.
SWAPS = {"Cyrl": ("abcdefghijklmnop", "абцдефгхийклмноп"), "Arab": ("abcdefghijklmnop", "ابتثجحخدذرزسشصضط"), "Hani": ("abcdefghijklmnop", "一二三四五六七八九十百千万上下中")}


def swapped(spark, sf):
    """Documents, some moved to another script."""
    t = F.col("text")
    for k, (a, b) in enumerate(SWAPS.values()):
        t = F.when(F.col("doc_id") % 7 == k, F.translate(F.lower("text"), a, b)).otherwise(t)
    return docs(spark, sf, "doc_id", "text", "lang").select("doc_id", t.alias("text"), lab.label_of("lang").alias("label"))


@query
def script_shares(spark, sf):
    s = scripts.count_letters(swapped(spark, sf).select("doc_id", "text"))
    counted = ("Latn", "Cyrl", "Arab", "Hani")
    places = list(scripts.PATTERNS)
    counts = [F.col("letters")[places.index(k) + 1].alias(k.lower()) for k in counted]
    return s.select("doc_id", *counts, scripts.main_of_counts(F.col("letters"), counted).alias("main"))


@query
def script_one_pass(spark, sf):
    return scripts.scripts_in_one_pass(swapped(spark, sf), ["doc_id"])


@query
def script_filter(spark, sf):
    rows = exploded_lines(swapped(spark, sf))
    return traindata.script_filter(rows).groupBy("label").agg(F.count(F.lit(1)).alias("n"))


@query
def admissible_labels(spark, sf):
    known = docs(spark, sf, "lang").select(lab.label_of("lang").alias("label")).union(spark.createDataFrame([("rus_Cyrl",), ("und_Mong",)], "label string"))
    return lab.by_script(known.distinct())


@query
def und_samples(spark, sf):
    return noise.undetermined_for(docs(spark, sf, "doc_id", "text"), ["Mong", "Newa", "Gran"])


@query
def noise_pdf(spark, sf):
    return noise.misrendered_pdf_for(docs(spark, sf, "doc_id", "text"))


@query
def noise_spaced(spark, sf):
    return docs(spark, sf, "doc_id", "text").select("doc_id", noise.spaced("text").alias("line"))


@query
def noise_binary(spark, sf):
    return noise.binary_for(docs(spark, sf, "doc_id", "text"))


@query
def noise_kinds(spark, sf):
    """Every kind of noise and some unseen scripts, as they are trained on."""
    return noise.rejects(spark, lines(spark, sf).filter("part < 8"), 20, "train", ["Mong", "Newa", "Gran", "Talu", "Sylo"])


@query
def noise_mojibake_latin(spark, sf):
    return docs(spark, sf, "doc_id", "text", "lang").filter("lang <> 'en'").select("doc_id", noise.mojibake_latin("text").alias("line"))


@query
def noise_mojibake_arabic(spark, sf):
    return docs(spark, sf, "doc_id", "text", "lang").filter("lang <> 'en'").select("doc_id", noise.mojibake_arabic("text").alias("line"))


@query
def noise_replacement(spark, sf):
    return docs(spark, sf, "doc_id", "text").select("doc_id", noise.replacement_char("text", "doc_id").alias("line"))


@query
def noise_harvest(spark, sf):
    seeds = spark.createDataFrame([("idiot",), ("!!",), ("###",)], "seed string")
    return noise.harvest(page_text(spark, sf).select("page_id", "text"), seeds)


RULES = [("rename", "spa_Latn", "es_new"), ("merge", "fra_Latn", "roa_Latn"), ("delete", "deu_Latn", None), ("keep", "eng_Latn", None)]


@query
def curation_rules(spark, sf):
    rows = lines(spark, sf).select("label")
    return curate.apply_rules(rows, spark.createDataFrame(RULES, curate.RULES)).groupBy("label").agg(F.count(F.lit(1)).alias("n"))


def weakest_f1(spark, sf):
    """F1 by label of a model with so few buckets that it hardly tells languages apart."""
    return evaluate.f1(weak_lines(spark, sf, model(spark, sf, buckets=4)))


@query
def curation_low_f1(spark, sf):
    return curate.low_labels(weakest_f1(spark, sf), 0.7)


@query
def curation_drop_labels(spark, sf):
    """Training lines that are left when the labels below the floor go."""
    low = curate.low_labels(weakest_f1(spark, sf), 0.7)
    return curate.drop_labels(lines(spark, sf), low).groupBy("label").agg(F.count(F.lit(1)).alias("n"))


#: Labels that stand for those of some documents, by the remainder of their number: macro-languages beside a member.
RELABELLED = {0: "swh_Latn", 1: "swa_Latn", 2: "quy_Latn", 3: "que_Latn"}


@query
def curation_exclusive(spark, sf):
    label = lab.label_of("lang")
    for k, other in RELABELLED.items():
        label = F.when(F.col("doc_id") % 5 == k, other).otherwise(label)
    return curate.check_exclusive(docs(spark, sf, "doc_id", "lang").select(label.alias("label")), lab.languages(spark))


@query
def label_mixture(spark, sf):
    return curate.mixture(weak_lines(spark, sf))


@query
def split_mass(spark, sf):
    scored = lid.probabilities(lid.scores(test_docs(spark, sf), weak(spark, sf), ["doc_id"], "text"), ["doc_id"], 4.0)
    return curate.split_mass(scored, spark.createDataFrame([("eng_Latn", "deu_Latn"), ("fra_Latn", "spa_Latn")], "a string, b string"), ["doc_id"])


@query
def train_split(spark, sf):
    return lines(spark, sf).groupBy("label", traindata.split_name().alias("split")).agg(F.count(F.lit(1)).alias("n"))


@query
def train_dedup(spark, sf):
    return traindata.dedup_exact(lines(spark, sf))


@query
def train_cap(spark, sf):
    return traindata.resample(lines(spark, sf), 100).select("label", "doc_id", "pos", "rank")


@query
def train_temperature(spark, sf):
    return traindata.resample_by_temperature(lines(spark, sf), 1000).select("label", "doc_id", "pos")


@query
def decontaminate_sentence(spark, sf):
    bench = traindata.bench_sentences(read(spark, sf, "benchmark"))
    return traindata.contained(lines(spark, sf), bench, ["doc_id", "pos"], "line")


@query
def decontaminate_document(spark, sf):
    bench = traindata.bench_sentences(read(spark, sf, "benchmark"))
    return traindata.contained(docs(spark, sf, "doc_id", "text"), bench, ["doc_id"], "text", min_share=0.8)


@query
def union_sources(spark, sf):
    a = docs(spark, sf, "text", "source").withColumn("provenance", F.lit("documents"))
    b = read(spark, sf, "conversations", "text").withColumn("provenance", F.lit("conversations"))
    return traindata.union_sources(a, b).groupBy("provenance").agg(F.count(F.lit(1)).alias("n"), F.count("source").alias("with_source"))


# ----------------------------------------------------------------------------------------------------- quality warnings


def injected(spark, sf):
    """Documents, some with phrases that the tables lack."""
    adds = ((0, " lorem ipsum dolor"), (1, " Read our Cookie Policy."), (2, " Please enable JavaScript."), (3, " {x}"), (4, " " + "w" * 101), (5, " " + "w" * 100))
    t = F.col("text")
    for k, phrase in adds:
        t = F.when(F.col("doc_id") % 13 == k, F.concat("text", F.lit(phrase))).otherwise(t)
    return docs(spark, sf, "doc_id", "text").select("doc_id", t.alias("text"))


def _warning(name: str, injected_text: bool = False):
    def run(spark, sf):
        d = injected(spark, sf) if injected_text else docs(spark, sf, "doc_id", "text")
        return d.filter(W.document_flags("text")[name]).select("doc_id")

    run.__name__ = {"short_sentences": "warn_short"}.get(name, f"warn_{name}")
    return query(run)


for _name in ("tiny", "short_sentences", "header", "footer", "list_case", "technical", "cursed", "repetition", "adult"):
    _warning(_name)
for _name in ("long_word", "filler", "policy", "js", "curly"):
    _warning(_name, True)


@query
def warn_list_case_any(spark, sf):
    from corpusforge.functions.text import lines as lines_of

    return docs(spark, sf, "doc_id", "text").filter(W.list_case(lines_of("text"), rule="any")).select("doc_id")


@query
def warn_list_case_uncased(spark, sf):
    """On texts moved to a script without case, spaces and all."""
    return swapped(spark, sf).filter(W.document_flags("text")["list_case_uncased"]).select("doc_id")


@query
def warn_lid_inconsistent(spark, sf):
    """At a lower threshold than the default, which no document reaches."""
    out = annotate.identify(docs(spark, sf, "doc_id", "text"), model(spark, sf))
    return out.filter(W.lid_inconsistent(F.transform("lines", lambda x: x["pred"]), F.col("pred"), W.Config(inconsistent=0.2))).select("doc_id", "pred")


@query
def warn_script_inconsistent(spark, sf):
    counted = scripts.count_letters(swapped(spark, sf))
    return counted.filter(W.script_inconsistent_counts(F.col("letters"), F.col("label"), W.technical("text"))).select("doc_id")


def annotated(spark, sf):
    return W.annotate(docs(spark, sf))


@query
def warn_all(spark, sf):
    return annotated(spark, sf).select("doc_id", F.array_join("warnings", ",").alias("warnings"))


@query
def warn_counts(spark, sf):
    return annotated(spark, sf).select(F.explode("warnings").alias("warning")).groupBy("warning").agg(F.count(F.lit(1)).alias("n"))


@query
def filter_document(spark, sf):
    return filters.keep_documents(annotated(spark, sf)).select("doc_id")


@query
def filter_line(spark, sf):
    return filters.keep_lines(lines(spark, sf)).groupBy("doc_id").agg(F.count(F.lit(1)).alias("n_lines"))


@query
def filter_no_word_boundary(spark, sf):
    """The exceptions for writing without word boundaries: the same documents as Japanese."""
    d = annotated(spark, sf).withColumn("label", F.when(F.col("doc_id") % 2 == 0, "jpn_Jpan").otherwise("eng_Latn"))
    return filters.keep_documents(d, "label").groupBy("label").agg(F.count(F.lit(1)).alias("n"))


@query
def calibration_sample(spark, sf):
    rows = lines(spark, sf).withColumn("script", F.lit("Latn")).withColumn("key", F.concat_ws("_", "label", "source"))
    return filters.calibration_sample(rows, "key")


@query
def warning_precision(spark, sf):
    return filters.warning_precision(annotated(spark, sf), read(spark, sf, "labels"))


# ---------------------------------------------------------------------------------------------------------------- corpus


@query
def html_text(spark, sf):
    t = page_text(spark, sf)
    return t.select("page_id", "host", "gold", F.length("text").alias("n"), (F.col("text").rlike("[<>]") | F.col("text").contains("function(")).alias("markup_left"))


@query
def content_classes(spark, sf):
    out = content.classify(read(spark, sf, "pages", "page_id", "url"), content.seed_list(spark))
    return out.select("page_id", "host", F.array_join("classes", ",").alias("classes"))


@query
def content_exclude(spark, sf):
    out = content.classify(read(spark, sf, "pages", "page_id", "url"), content.extend(content.seed_list(spark), "blog", ["blog.example.com"]))
    return content.exclude(out, ["adult", "spam", "blog"]).select("page_id")


@query
def pii_email(spark, sf):
    d = docs(spark, sf, "doc_id", "text")
    return d.filter(F.col("text").rlike(pii.EMAIL)).select("doc_id", F.md5(pii.emails("text")).alias("h"))


@query
def pii_ip(spark, sf):
    d = docs(spark, sf, "doc_id", "text")
    return d.filter(F.col("text").rlike(pii.QUAD)).select("doc_id", F.md5(pii.ips("text")).alias("h"))


@query
def pii_report(spark, sf):
    p = docs(spark, sf, "doc_id", "text").select("doc_id", pii.counts("text").alias("p"))
    return p.filter("p.email + p.ip + p.private_ip > 0").select("doc_id", F.col("p.email").alias("email"), F.col("p.ip").alias("ip"), F.col("p.private_ip").alias("private_ip"))


@query
def lsh_digest(spark, sf):
    return lsh.digests(docs(spark, sf, "doc_id", "text"), "doc_id")


@query
def lsh_distance_pairs(spark, sf):
    """Documents against themselves with one word added, and against the next document."""
    d = lsh.digests(docs(spark, sf, "doc_id", "text"), "doc_id").filter("lsh_digest is not null")
    changed = lsh.digests(docs(spark, sf, "doc_id", "text").select("doc_id", F.concat("text", F.lit(" word")).alias("text")), "doc_id").filter("lsh_digest is not null")
    a = d.select(F.col("doc_id").alias("a"), F.col("lsh_digest").alias("digest_a"))
    own = a.join(changed.select(F.col("doc_id").alias("b"), F.col("lsh_digest").alias("digest_b")), F.col("a") == F.col("b"))
    other = a.join(d.select(F.col("doc_id").alias("b"), F.col("lsh_digest").alias("digest_b")), F.col("b") == F.col("a") + 1)
    return lsh.distances(own.unionByName(other)).groupBy((F.col("a") == F.col("b")).alias("same")).agg(F.count(F.lit(1)).alias("n"), F.round(F.avg("distance"), 2).alias("mean"))


@query
def dedup_exact(spark, sf):
    return dedup.exact(docs(spark, sf, "doc_id", "text"))


@query
def dedup_near(spark, sf):
    return dedup.near(docs(spark, sf, "doc_id", "text"))


def raw_corpus(spark, sf):
    """What a crawl gives: the documents beside noise and lines of unseen scripts."""
    return docs(spark, sf, "doc_id", "text", "source").union(noise_docs(spark, sf).select("doc_id", "text", F.lit("noise")))


def corpus(spark, sf, labels=None, **changes):
    """The run with the third release, or with a closed set of labels in its place."""
    m = model(spark, sf, labels) if labels else release(spark, sf, "r3")
    return pipeline.run(raw_corpus(spark, sf), pipeline.Config(model=m).but(**changes))


@query
def pipeline_kept(spark, sf):
    k = corpus(spark, sf).kept
    return k.select("doc_id", "label", F.array_join("warnings", ",").alias("warnings"), F.md5("text").alias("h"), F.col("pii.email").alias("email"), F.col("pii.ip").alias("ip"))


@query
def pipeline_stats(spark, sf):
    return corpus(spark, sf).stats()


#: A closed set without one language and without reject labels, as the models the third release is compared with.
CLOSED = ("eng_Latn", "fra_Latn", "deu_Latn")


@query
def pipeline_swap(spark, sf):
    """The same pipeline with another identifier."""
    return corpus(spark, sf, CLOSED).stats()


@query
def pipeline_counters(spark, sf):
    """Counters of the stages, observed while the corpus is written."""
    counters = Observation("stages")
    pipeline.run(raw_corpus(spark, sf), pipeline.Config(model=release(spark, sf, "r3")), counters).kept.write.format("noop").mode("overwrite").save()
    return spark.createDataFrame([(k, int(v)) for k, v in counters.get.items()], "counter string, n long")


@query
def coverage_retention_predicted(spark, sf):
    """By the label that the run gave: documents, kept ones, size of the language."""
    rows = corpus(spark, sf).rows.filter(~pipeline.is_rejected("label")).select("label", "reason")
    t = rows.groupBy("label").agg(F.count(F.lit(1)).alias("n_in"), F.count(F.when(F.col("reason").isNull(), 1)).alias("n_kept"))
    return t.select("label", coverage.size_bucket("n_in").alias("bucket"), "n_in", "n_kept", F.round(F.col("n_kept") / F.col("n_in"), 6).alias("share"))


@query
def coverage_prior_corpus(spark, sf):
    """Our corpus by its labels against one that a closed-set identifier with a threshold makes of the same pages without filters."""
    ours = corpus(spark, sf).kept.select("label")
    prior = annotate.identify_rows(raw_corpus(spark, sf), model(spark, sf, CLOSED), by=annotate.Pass(lines=False))
    return coverage.compare(ours, lid.reject(prior, 0.8).filter("pred is not null").select(F.col("pred").alias("label")), "label")


def prefix(spark, sf):
    """The first tenth of the documents, as the comparison of two runs takes a prefix of a snapshot."""
    d = docs(spark, sf, "doc_id", "text", "source")
    return d.join(F.broadcast(d.agg(F.max("doc_id").alias("last"))), F.col("doc_id") * 10 <= F.col("last")).drop("last")  # one row


@query
def compare_pipelines(spark, sf):
    """Two whole runs over the same prefix that differ in the identifier alone: what becomes of each page, in numbers."""
    d, cfg = prefix(spark, sf), pipeline.Config()
    runs = [pipeline.run(d, cfg.but(model=m)).kept.select("doc_id", F.col("label").alias("pred")) for m in (model(spark, sf), model(spark, sf, CLOSED))]
    return compare.joined(*runs).groupBy(F.coalesce("label_a", F.lit("none")).alias("label_a"), F.coalesce("label_b", F.lit("none")).alias("label_b")).agg(F.count(F.lit(1)).alias("n"))


@query
def pipeline_snapshots(spark, sf):
    d = docs(spark, sf)
    parts = {"2024-10": d, "2024-18": d.filter("doc_id % 3 = 0"), "2024-22": d.filter("doc_id % 5 = 0")}
    return pipeline.run_snapshots(parts).groupBy("snapshot").agg(F.count(F.lit(1)).alias("n"))


def pseudo(d):
    return d.withColumn("key", F.concat_ws("_", "lang", "source"))


@query
def coverage_buckets(spark, sf):
    return coverage.size_buckets(pseudo(docs(spark, sf)), "key")


@query
def coverage_compare(spark, sf):
    """Our corpus against one without filters."""
    return coverage.compare(filters.keep_documents(annotated(spark, sf)), docs(spark, sf), "lang")


@query
def coverage_area(spark, sf):
    t = coverage.by_area(docs(spark, sf).withColumn("label", lab.label_of("lang")), "label", lab.languages(spark))
    return t.na.fill("all", ["area"]).na.fill(-1, ["bucket"])


#: Labels from other areas and of constructed languages, by the remainder of a document's number.
ABROAD = {0: "swh_Latn", 1: "quy_Latn", 2: "epo_Latn", 3: "tlh_Latn"}


@query
def coverage_area_constructed(spark, sf):
    """The areas where some documents pass for other languages, since all those of the tables are of one area."""
    label = lab.label_of("lang")
    for k, other in ABROAD.items():
        label = F.when(F.col("doc_id") % 7 == k, other).otherwise(label)
    t = coverage.by_area(docs(spark, sf, "doc_id", "lang").select(label.alias("label")), "label", lab.languages(spark))
    return t.na.fill("all", ["area"]).na.fill(-1, ["bucket"])


@query
def coverage_area_surrogate(spark, sf):
    """Customers by nation and region, as documents by language and area."""
    c = read(spark, sf, "customer", "c_nationkey").join(F.broadcast(read(spark, sf, "nation")), F.col("c_nationkey") == F.col("n_nationkey")).join(F.broadcast(read(spark, sf, "region")), F.col("n_regionkey") == F.col("r_regionkey"))  # nation and region have a fixed number of rows
    return c.cube("r_name", "n_name").agg(F.count(F.lit(1)).alias("n"))


@query
def coverage_class_share(spark, sf):
    p = read(spark, sf, "pages", "page_id", "url", "html")
    out = content.classify(p, content.seed_list(spark)).join(p.select("page_id", html.html_lang("html").alias("lang")), "page_id")
    return coverage.class_share(out, "lang")


@query
def coverage_contamination(spark, sf):
    return coverage.contamination(weak_lines(spark, sf), ["eng_Latn"])


@query
def coverage_retention(spark, sf):
    return coverage.retention(docs(spark, sf), filters.keep_documents(annotated(spark, sf)), "lang")


@query
def wall_time(spark, sf):
    """Hours by the published rates for one snapshot, and for the given table."""
    s = exploded_lines(docs(spark, sf, "doc_id", "text")).count()
    d = docs(spark, sf, "doc_id").agg(F.count(F.lit(1)).alias("d"))
    ours = d.select(F.lit("given table").alias("corpus"), F.round(cost.wall_hours(F.col("d"), 48.0, F.lit(s) / F.col("d"), 1379.0, 245.0), 9).alias("hours"))
    return ours.union(spark.range(1).select(F.lit("snapshot"), F.round(cost.wall_hours(F.lit(3.16e9), 48.0, 20.0, 1379.0, 245.0), 4)))


@query
def audit_sample(spark, sf):
    return audit.sample(pseudo(docs(spark, sf)), "key", 40)


#: Words below which the auditor can't tell a language.
TOO_SHORT = 10


@query
def audit_score(spark, sf):
    """Only the sampled documents are identified; those that are too short have no verdict."""
    s = audit.sample(pseudo(docs(spark, sf)), "key", 40)  # some hundred rows
    own = docs(spark, sf, "doc_id", "text", "lang").join(F.broadcast(s), "doc_id")
    p = annotate.identify_rows(own, model(spark, sf), by=annotate.Pass(lines=False)).filter("pred is not null")
    judged = p.withColumn("verdict", F.when(F.size(words("text")) >= TOO_SHORT, (F.col("pred") == lab.label_of("lang")).cast("int")))
    return audit.score(judged)


@query
def audit_undeterminable(spark, sf):
    """Sampled documents that the auditor can't judge."""
    s = audit.sample(pseudo(docs(spark, sf)), "key", 40)
    own = docs(spark, sf, "doc_id", "text").join(F.broadcast(s), "doc_id")
    return own.filter(F.size(words("text")) < TOO_SHORT).select("label", "doc_id")


@query
def audit_out_of_model(spark, sf):
    """A model that lacks a language: the audit meets that language under other labels."""
    m = model(spark, sf, CLOSED)
    p = predicted(spark, sf, m)
    found = audit.out_of_model(p.select(F.col("gold").alias("label")), m.totals)
    called = p.groupBy(F.col("gold").alias("label")).agg(F.count("pred").alias("called"), F.round(F.avg("prob"), 4).alias("mean_prob"))
    return found.join(called, "label")


@query
def audit_clues(spark, sf):
    return audit.clues(read(spark, sf, "pages", "page_id", "url", "html"))


@query
def audit_affix(spark, sf):
    return audit.affix_repetition(docs(spark, sf, "doc_id", "text"))


@query
def audit_recleanse(spark, sf):
    d = docs(spark, sf).withColumn("label", lab.label_of("lang"))
    return audit.recleanse(d, spark.createDataFrame([("spa_Latn",)], "label string")).groupBy("label").agg(F.count(F.lit(1)).alias("n"))


def two_runs(spark, sf):
    """Two identifiers over held-out documents, with pseudo-labels as rare labels."""
    test = test_docs(spark, sf)
    keys = docs(spark, sf, "doc_id", "source")
    a = predicted(spark, sf).select("doc_id", "pred")
    b = lid.reject(predicted(spark, sf, model(spark, sf, CLOSED)), 0.8).select("doc_id", "pred")
    with_source = lambda p: p.join(keys, "doc_id").select("doc_id", F.when(F.col("pred").isNotNull(), F.concat_ws("_", "pred", "source")).alias("pred"))
    truth = test.select("doc_id", "gold").join(keys, "doc_id").select("doc_id", F.concat_ws("_", "gold", "source").alias("truth"))
    return with_source(a), with_source(b), truth


@query
def compare_disagree(spark, sf):
    a, b, truth = two_runs(spark, sf)
    return compare.rare(compare.joined(a, b)).join(truth, "doc_id")


@query
def compare_outcomes(spark, sf):
    a, b, truth = two_runs(spark, sf)
    return compare.outcomes(compare.chosen(compare.rare(compare.joined(a, b))).join(truth, "doc_id"))


@query
def compare_extrapolate(spark, sf):
    a, b, _ = two_runs(spark, sf)
    n = compare.rare(compare.joined(a, b)).agg(F.count(F.lit(1)).alias("n"))
    return n.select("n", compare.extrapolate(F.col("n"), 0.1, 100).alias("pages"), F.lit(compare.extrapolate(260, 0.01, 100)).alias("published"))


@query
def compare_call_rate(spark, sf):
    a, b, _ = two_runs(spark, sf)
    return compare.call_rate(a, "a").union(compare.call_rate(b, "b"))


QUERIES |= relational.QUERIES | stream.QUERIES
