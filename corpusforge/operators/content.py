"""Content classes of sites by lists of domains. Classes annotate; removal is the user's choice."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from corpusforge.functions.html import host

#: Seed list for the given pages; real lists have millions of rows and come as tables. The two classes added to
#: the list of others are encyclopedia and religious; some of the given hosts stand in for religious sites.
SEEDS = (
    ("cheap-pills.example.com", "drugs"), ("spam-farm.example.org", "spam"), ("casino-win.example.org", "gambling"), ("adult-x.example.net", "adult"),
    ("wiki.example.org", "encyclopedia"), ("news.example.com", "press"), ("example.net", "network"),
    ("wikipedia.org", "encyclopedia"), ("jw.org", "religious"), ("ebible.com", "religious"), ("thther.example.org", "religious"), ("tionsh.example.net", "religious"), ("ththan.example.net", "religious"),
)


def seed_list(spark: SparkSession) -> DataFrame:
    return spark.createDataFrame(SEEDS, "domain string, class string")


def extend(lists: DataFrame, cls: str, domains: list[str]) -> DataFrame:
    """The list with a class of one's own."""
    return lists.union(lists.sparkSession.createDataFrame([(d, cls) for d in domains], lists.schema)).distinct()


def suffixes(host_col: str = "host"):
    """A host and its parent domains, down to two labels."""
    parts = F.split(host_col, r"\.")
    return F.when(F.size(parts) >= 2, F.transform(F.sequence(F.lit(1), F.size(parts) - 1), lambda i: F.array_join(F.slice(parts, i, F.size(parts)), "."))).otherwise(F.array(F.col(host_col)))


def classify(pages: DataFrame, lists: DataFrame, key: str = "page_id", url: str = "url") -> DataFrame:
    """(key, host, classes): sorted classes of the lists' domains that the host lies under, empty if none.

    Distinct hosts are matched, not pages, so a giant host costs one row; Spark broadcasts the list while it is small.
    """
    hosted = pages.select(key, host(url).alias("host"))
    found = hosted.select("host").distinct().select("host", F.explode(suffixes()).alias("domain")).join(lists, "domain").groupBy("host").agg(F.array_sort(F.collect_set("class")).alias("classes"))
    return hosted.join(found, "host", "left").select(key, "host", F.coalesce("classes", F.expr("cast(array() as array<string>)")).alias("classes"))


def exclude(classified: DataFrame, unwanted: list[str]) -> DataFrame:
    return classified.filter(~F.arrays_overlap("classes", F.array(*[F.lit(c) for c in unwanted])))
