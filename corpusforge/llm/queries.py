"""The queries of this subpackage: one for each operator, over its whole table and with production parameters."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from corpusforge.engine import read
from corpusforge.llm.encoding import tokenizer_path

Query = Callable[[SparkSession, str], DataFrame]


def op1_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    from corpusforge.llm.tokencount import token_counts

    return token_counts(read(spark, sf_dir, "documents", "doc_id", "text"), tokenizer_path("piece_bpe_32k.model"))


def op2_sharding(spark: SparkSession, sf_dir: str) -> DataFrame:
    from corpusforge.llm.shards import compacted

    return compacted(spark, sf_dir)


def op3_licenses(spark: SparkSession, sf_dir: str) -> DataFrame:
    from pyspark.sql import functions as F

    from corpusforge.llm.licenses import scan

    found = scan(read(spark, sf_dir, "documents", "doc_id", "text"))
    return found.select("doc_id", "n_sentences", F.array_join("sentence_ids", ",").alias("sentence_ids"), F.array_join("licenses", ",").alias("licenses"))


def op4_language(spark: SparkSession, sf_dir: str) -> DataFrame:
    from corpusforge.llm.bytecnn import identify

    return identify(read(spark, sf_dir, "documents", "doc_id", "lang", "text"))


def op5_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    from corpusforge.llm.decontaminate import contaminated

    return contaminated(read(spark, sf_dir, "documents", "doc_id", "text"), read(spark, sf_dir, "benchmark", "item_id", "text"))


def op6_near_vectors(spark: SparkSession, sf_dir: str) -> DataFrame:
    from corpusforge.llm.pivots import near_vectors

    return near_vectors(read(spark, sf_dir, "embeddings", "vec_id", "embedding", "label"))


def op7_token_files(spark: SparkSession, sf_dir: str) -> DataFrame:
    from corpusforge.llm.tokenfiles import round_trip

    return round_trip(read(spark, sf_dir, "documents", "doc_id", "text"), tokenizer_path("byte_bpe_50k.json"), end_id=0)


def op8_secrets(spark: SparkSession, sf_dir: str) -> DataFrame:
    from corpusforge.llm.secrets import report, scan

    return report(scan(read(spark, sf_dir, "documents", "doc_id", "text")))


def op9_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    from corpusforge.llm.packing import pack

    return pack(read(spark, sf_dir, "documents", "doc_id", "text"), tokenizer_path("word_bpe_49k.json"), end_id=1)


def op10_simhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    from corpusforge.llm.simhash import near_duplicates, with_hex

    return with_hex(near_duplicates(read(spark, sf_dir, "documents", "doc_id", "text")))


QUERIES: dict[str, Query] = {f.__name__: f for f in (op1_token_counts, op2_sharding, op3_licenses, op4_language, op5_decontamination, op6_near_vectors, op7_token_files, op8_secrets, op9_packing, op10_simhash)}

#: DuckDB twins, where SQL can express the operator.
ORACLES: dict[str, str] = {
    "op2_sharding": "select doc_id, md5(text) as text_md5, lang, source, n_chars from documents",
    "op6_near_vectors": """with recursive rows as (select row_number() over () as r, vec_id, label, cast(embedding as double[]) as e from embeddings),
fit as (select *, len(e) as d from rows where vec_id is not null and label is not null and coalesce(len(list_filter(e, lambda x: x is null or not isfinite(x))) = 0 and len(list_filter(e, lambda x: x <> 0)) > 0, false)),
unit as (select r, vec_id, label, d, [x / norm for x in e] as u from (select *, sqrt(list_sum([x * x for x in e])) as norm from fit)),
links as (select x.r as a, y.r as b from unit x join unit y on x.label = y.label and x.d = y.d and x.r <> y.r where list_dot_product(x.u, y.u) >= 0.93),
reach as (select r as a, r as b from fit union select reach.a, links.b from reach join links on reach.b = links.a),
least as (select a, min(vec_id) as component_id from reach join fit on b = r group by 1),
counts as (select a, count(*) as n from links group by 1)
select vec_id, coalesce(n, 0) as n_links, coalesce(component_id, vec_id) as component_id, coalesce(vec_id = component_id, true) as kept from rows left join counts c on c.a = rows.r left join least l on l.a = rows.r""",
}
