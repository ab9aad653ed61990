"""The cheap methods as SQL functions, so that the pipeline can be typed as a query."""

from __future__ import annotations

import re
import uuid

import pyarrow as pa
from pyspark.sql import SparkSession
from pyspark.sql import functions as F

from corpusforge.operators.lid import LidModel

#: Name, argument and body of functions that the analyzer inlines.
FUNCTIONS = {
    "text_lines": "filter(transform(split(t, '\\n'), x -> trim(x)), x -> x <> '')",
    "warn_tiny": "size(filter(split(t, '\\n'), x -> trim(x) <> '')) < 3",
    "warn_policy": "lower(t) rlike 'terms of use|privacy policy|cookie policy|uses cookies|use of cookies|use cookies'",
    "warn_js": "t rlike 'Java[Ss]cript'",
    "warn_curly": "t rlike '[{}]'",
    "warn_long_word": "t rlike '[^ \\t\\r\\n]{101,}'",
    "host_suffixes": "case when size(split(t, '[.]')) >= 2 then transform(sequence(1, size(split(t, '[.]')) - 1), i -> array_join(slice(split(t, '[.]'), i, size(split(t, '[.]'))), '.')) else array(t) end",
    "warn_filler": "contains(lower(t), 'lorem ipsum')",
}


def register(spark: SparkSession) -> None:
    """Register scalar functions, the digest, and tables of lines and n-grams."""
    from pyspark.sql.types import LongType, StringType

    from corpusforge.engine import ship
    from corpusforge.functions import lsh, marks
    from corpusforge.functions.scripts import PATTERNS
    from corpusforge.functions.text import letter_class

    ship(spark)
    for name, body in FUNCTIONS.items():
        kind = "array<string>" if name in ("text_lines", "host_suffixes") else "boolean"
        spark.sql(f"create or replace temporary function {name}(t string) returns {kind} return {body}")

    @F.arrow_udf(StringType())
    def lsh_digest(texts: pa.Array) -> pa.Array:
        return pa.array([lsh.digest(t) for t in texts.to_pylist()], pa.string())

    @F.arrow_udf(LongType())
    def lsh_distance(a: pa.Array, b: pa.Array) -> pa.Array:
        return pa.array([None if x is None or y is None else lsh.distance(x, y) for x, y in zip(a.to_pylist(), b.to_pylist(), strict=True)], pa.int64())

    @F.arrow_udf(StringType())
    def script_of(texts: pa.Array) -> pa.Array:
        """The script of most letters of a text, the first by name of equals."""
        names, out = sorted(PATTERNS), []
        for t in texts.to_pylist():
            counts = dict(zip(PATTERNS, marks.letters(marks.code_classes(t or ""))[1:], strict=True))
            best = max(names, key=lambda s: counts[s])
            out.append(best if counts[best] else None)
        return pa.array(out, pa.string())

    # plain table functions: Spark refuses lateral joins with those over Arrow batches
    @F.udtf(returnType="pos int, line string")
    class LineTable:
        def eval(self, text: str):
            for pos, line in enumerate((text or "").split("\n")):
                if s := line.strip(" "):
                    yield pos, s

    word = re.compile(f"{letter_class()}+")

    @F.udtf(returnType="gram string")
    class NgramTable:
        def eval(self, text: str, nmin: int, nmax: int):
            for padded in (f" {w} " for w in word.findall((text or "").lower())):
                for n in range(nmin, nmax + 1):
                    yield from ((padded[i : i + n],) for i in range(len(padded) - n + 1))

    spark.udf.register("lsh_digest", lsh_digest)
    spark.udf.register("lsh_distance", lsh_distance)
    spark.udf.register("script_of", script_of)
    spark.udtf.register("line_table", LineTable)
    spark.udtf.register("ngram_table", NgramTable)


def register_model(spark: SparkSession, model: LidModel, name: str = "lid_label") -> None:
    """Register ``name(text)``, the label that a counting model gives; the model must be within the broadcast limit."""
    from pyspark.sql.types import StringType

    from corpusforge.engine import ship, worker_state
    from corpusforge.plans import annotate

    ship(spark)
    if model.counts.count() > annotate.BROADCAST_PAIRS:
        raise ValueError("the model is too large for a function; identify documents by join")
    holder, pattern = spark.sparkContext.broadcast(annotate.Model(model)), model.pattern
    key = uuid.uuid4().hex

    @F.arrow_udf(StringType())
    def label(texts: pa.Array) -> pa.Array:
        scorer = worker_state((key, pattern), lambda: annotate.Scorer(holder.value, pattern))
        return annotate._batch(scorer, texts.to_pylist(), annotate.Pass(lines=False), None)[0]

    spark.udf.register(name, label)
