"""Labels of language and script, and what is known of languages."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from corpusforge.functions.text import col

#: Labels of the two-letter codes in the given tables.
LABELS = {"en": "eng_Latn", "fr": "fra_Latn", "de": "deu_Latn", "es": "spa_Latn"}
#: Languages written without spaces between words (ISO 639-3).
NO_WORD_BOUNDARY = ("bod", "cmn", "dzo", "jpn", "khm", "lao", "lzh", "mya", "nan", "tha", "wuu", "yue", "zho")
#: Constructed languages of ISO 639-3, with the script they are written in.
CONSTRUCTED = (
    "afh_Latn", "avk_Latn", "bzt_Latn", "dws_Latn", "epo_Latn", "ido_Latn", "igs_Latn", "ile_Latn", "ina_Latn", "jbo_Latn", "ldn_Latn",
    "lfn_Latn", "neu_Latn", "nov_Latn", "qya_Latn", "rmv_Latn", "sjn_Latn", "tlh_Latn", "tzl_Latn", "vol_Latn", "zba_Arab", "zbl_Blis",
)
#: Fixed values: (label, macro-area, constructed, macro-language).
LANGUAGES = (
    ("eng_Latn", "Eurasia", False, None),
    ("fra_Latn", "Eurasia", False, None),
    ("deu_Latn", "Eurasia", False, None),
    ("spa_Latn", "Eurasia", False, None),
    ("swh_Latn", "Africa", False, "swa"),
    ("jpn_Jpan", "Eurasia", False, None),
    ("quy_Latn", "South America", False, "que"),
    *((label, None, True, None) for label in CONSTRUCTED),
)
#: Scripts in which a language is written (ISO 15924).
ADMISSIBLE = {
    "eng": ("Latn",), "fra": ("Latn",), "deu": ("Latn",), "spa": ("Latn",), "rus": ("Cyrl",), "srp": ("Cyrl", "Latn"), "ara": ("Arab",),
    "cmn": ("Hani",), "jpn": ("Hani", "Hira", "Kana"), "ell": ("Grek",), "hin": ("Deva",), "kaz": ("Cyrl", "Arab", "Latn"),
}
#: Codes that stand for several scripts written together.
COMPOSITE = {"Jpan": ("Hani", "Hira", "Kana"), "Kore": ("Hang", "Hani"), "Hans": ("Hani",), "Hant": ("Hani",)}


def label_of(lang: Column | str) -> Column:
    return F.element_at(F.create_map(*[F.lit(x) for pair in LABELS.items() for x in pair]), col(lang))


def compose(iso: Column | str, script: Column | str, separator: str = "_") -> Column:
    return F.concat_ws(separator, col(iso), col(script))


def parse(label: Column | str) -> Column:
    """(iso, script, kind) of a label with either separator; kind is lang, und or zxx."""
    iso = F.regexp_extract(col(label), "^([a-z]{3})[-_]", 1)
    kind = F.when(iso == "und", "und").when(iso == "zxx", "zxx").otherwise("lang")
    return F.struct(iso.alias("iso"), F.regexp_extract(col(label), "^[a-z]{3}[-_](.+)$", 1).alias("script"), kind.alias("kind"))


def admissible(spark: SparkSession) -> DataFrame:
    return spark.createDataFrame([(iso, s) for iso, scripts in ADMISSIBLE.items() for s in scripts], "iso string, script string")


def languages(spark: SparkSession) -> DataFrame:
    return spark.createDataFrame(LANGUAGES, "label string, macroarea string, constructed boolean, macro_label string")


def by_script(labels: DataFrame) -> DataFrame:
    """Labels that each script allows."""
    return labels.groupBy(parse("label")["script"].alias("script")).agg(F.array_join(F.array_sort(F.collect_set("label")), ",").alias("labels"))


def word_based(label: Column | str) -> Column:
    """Whether words of a label's language are separated, so that word statistics mean something."""
    return ~parse(label)["iso"].isin(*NO_WORD_BOUNDARY)
