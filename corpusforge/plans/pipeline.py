"""The corpus run: identify, drop reject labels, warn, filter, anonymise, digest, write. The identifier is a plug-in."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass, replace

from pyspark.sql import DataFrame, Observation
from pyspark.sql import functions as F

from corpusforge.functions import lsh, pii
from corpusforge.functions import warnings as W
from corpusforge.functions.scripts import count_letters
from corpusforge.operators import filters
from corpusforge.operators.lid import LidModel
from corpusforge.plans import annotate

#: An identifier takes documents and gives (doc_id, pred, prob, lines), or the documents themselves with these columns.
Identifier = Callable[[DataFrame], DataFrame]


@dataclass(frozen=True)
class Config:
    """``model`` is identified in the pass that also raises the warnings; ``lid`` is any other identifier."""

    model: LidModel | None = None
    restrict: bool = False
    lid: Identifier | None = None
    warnings: W.Config = W.DEFAULT
    filter: bool = True
    drop_rejected: bool = True
    replace_pii: bool = True
    digest: bool = False

    def but(self, **changes) -> Config:
        return replace(self, **changes)

    @property
    def identifies(self) -> bool:
        return self.model is not None or self.lid is not None


@dataclass
class CorpusResult:
    #: Every document with its label, warnings and the reason for which it is dropped, or null.
    rows: DataFrame
    kept: DataFrame

    @property
    def dropped(self) -> DataFrame:
        return self.rows.filter("reason is not null").drop("line_labels", "letters")

    def stats(self) -> DataFrame:
        """(label, reason, n): kept documents, and dropped ones by what they were dropped for; texts are not rewritten for it."""
        return self.rows.groupBy("label", F.coalesce("reason", F.lit("kept")).alias("reason")).agg(F.count(F.lit(1)).alias("n"))


def is_rejected(label) -> F.Column:
    """Labels that stand for no language, and misses."""
    return F.col(label).isNull() | F.col(label).rlike("^(und|zxx)_")


def _identified(docs: DataFrame, cfg: Config) -> DataFrame:
    """Documents with label, prob, line_labels, letters and named (the warnings of the text alone)."""
    labels = F.transform("lines", lambda x: x["pred"])
    if cfg.model is not None:
        found = annotate.identify_rows(docs, cfg.model, by=annotate.Pass(restrict=cfg.restrict, letters=True, warnings=cfg.warnings))
        return found.withColumn("line_labels", labels).withColumnRenamed("pred", "label").drop("lines")
    rows = docs
    if cfg.lid is not None:
        found = cfg.lid(docs)
        if "text" not in found.columns:
            found = docs.join(found.select("doc_id", "pred", "prob", "lines"), "doc_id", "left")
        rows = found.withColumn("line_labels", labels).withColumnRenamed("pred", "label").drop("lines")
    else:
        rows = rows.withColumn("label", F.lit(None).cast("string")).withColumn("prob", F.lit(None).cast("double")).withColumn("line_labels", F.expr("cast(array() as array<string>)"))
    return count_letters(W.annotate(rows, cfg.warnings).withColumnRenamed("warnings", "named"))


def run(docs: DataFrame, cfg: Config = Config(), counters: Observation | None = None) -> CorpusResult:
    """Kept and dropped documents with label, warnings and counts of replaced data; ``counters`` observes the stages.

    A narrow plan over the scan: one Arrow pass identifies and warns, then columns decide. The pass ends the expressions
    below it, so what it gave is computed once however often it is used.
    """
    rows = _identified(docs, cfg)
    named = F.coalesce("named", F.expr("cast(array() as array<string>)"))
    if cfg.identifies:
        inconsistent = {
            "lid_inconsistent": W.lid_inconsistent(F.col("line_labels"), F.col("label"), cfg.warnings),
            "script_inconsistent": W.script_inconsistent_counts(F.col("letters"), F.col("label"), F.array_contains("named", "technical"), cfg.warnings),
        }
        named = F.concat(named, W.named(inconsistent))
    rows = rows.withColumn("warnings", named).drop("named", "letters")
    rejected = is_rejected("label") if cfg.identifies and cfg.drop_rejected else F.lit(False)
    cost = filters.costly(F.col("warnings"), F.coalesce("label", F.lit("eng_Latn"))) if cfg.filter else F.expr("cast(array() as array<string>)")
    rows = rows.withColumn("reason", F.when(rejected, F.lit("rejected")).when(F.size(cost) > 0, F.element_at(cost, 1)))
    if counters is not None:
        one = lambda c: F.count(F.when(c, 1))
        rows = rows.observe(counters, F.count(F.lit(1)).alias("read"), one(F.col("reason") == "rejected").alias("rejected"), one(F.col("reason") != "rejected").alias("filtered"), one(F.col("reason").isNull()).alias("kept"))
    kept = rows.filter("reason is null").drop("reason", "line_labels")
    if cfg.replace_pii:
        kept = kept.withColumn("pii", pii.counts("text")).withColumn("text", pii.apply("text"))
    if cfg.digest:
        kept = lsh.with_digests(kept)
    return CorpusResult(rows, kept)


def run_snapshots(snapshots: dict[str, DataFrame], cfg: Config = Config()) -> DataFrame:
    """Kept documents of several snapshots, each with its name."""
    out = None
    for name, docs in snapshots.items():
        part = run(docs, cfg).kept.withColumn("snapshot", F.lit(name))
        out = part if out is None else out.unionByName(part, allowMissingColumns=True)
    return out
