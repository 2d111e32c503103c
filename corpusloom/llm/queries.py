"""The thin queries over the operators of this subpackage, and their SQL where SQL can say the same."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from corpusloom.llm import bpe, exact_dedup, flac, html_text, licences, packing, pii, simhash, token_files, toxicity, vocab
from corpusloom.runtime import table, texts


def op1_html_line_blocks(spark: SparkSession, sf_dir: str) -> DataFrame:
    return html_text.extract(texts(spark, sf_dir, "pages"))


def op2_simhash_near_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return simhash.near_duplicates(texts(spark, sf_dir, "documents"))


def op3_pii_boosted(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = texts(spark, sf_dir, "documents")
    return pii.digests(docs, pii.fit(docs))


def op4_licence_digests(spark: SparkSession, sf_dir: str) -> DataFrame:
    return licences.scan(texts(spark, sf_dir, "documents"))


def op5_separator_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    return token_files.document_counts(texts(spark, sf_dir, "documents"), vocab.at("word_bpe_49k.json"), end_id=49407)


def op6_toxicity_kernel_svm(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = texts(spark, sf_dir, "documents")
    return toxicity.score(docs, toxicity.fit(docs, table(spark, sf_dir, "labels")))


def op7_flac_media(spark: SparkSession, sf_dir: str) -> DataFrame:
    return flac.digests(texts(spark, sf_dir, "documents"))


def op8_best_fit_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    # Workers that do nothing else have room for a larger cache.
    pieces = packing.document_pieces(texts(spark, sf_dir, "documents"), vocab.at("word_bpe_49k.json"), cache=900_000, block_chars=8_000_000)
    return packing.pack(pieces)[0]


def op9_byte_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    return bpe.digests(texts(spark, sf_dir, "documents"), vocab.at("byte_bpe_multi_50k.tiktoken"))


def op10_exact_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return exact_dedup.exact_duplicates(texts(spark, sf_dir, "documents"))


QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    "op1_html_line_blocks": op1_html_line_blocks,
    "op2_simhash_near_dedup": op2_simhash_near_dedup,
    "op3_pii_boosted": op3_pii_boosted,
    "op4_licence_digests": op4_licence_digests,
    "op5_separator_scan": op5_separator_scan,
    "op6_toxicity_kernel_svm": op6_toxicity_kernel_svm,
    "op7_flac_media": op7_flac_media,
    "op8_best_fit_packing": op8_best_fit_packing,
    "op9_byte_bpe": op9_byte_bpe,
    "op10_exact_dedup": op10_exact_dedup,
}

#: The pages of the given tables have one article element each, of headings and paragraphs; SQL can cut that out.
_ARTICLE = r"""
    WITH a AS (SELECT page_id, url, regexp_extract(coalesce(html, ''), '(?s)<article>(.*?)(?:</article>|\z)', 1) AS body FROM pages),
    b AS (SELECT page_id, url, list_transform(regexp_split_to_array(body, '</?(?:p|h1)>'),
        lambda x: trim(regexp_replace(replace(replace(replace(replace(replace(regexp_replace(replace(x, '<br>', ' '), '</?b>', '', 'g'), '&lt;', '<'), '&gt;', '>'), '&quot;', '"'), '&#39;', chr(39)), '&amp;', '&'), '[ \t\r\n]+', ' ', 'g'))) AS parts FROM a),
    c AS (SELECT page_id, url, array_to_string(list_filter(parts, lambda x: x <> ''), chr(10) || chr(10)) AS text FROM b)
    SELECT page_id, url, text, length(text) AS n_chars FROM c
"""

ORACLES: dict[str, str] = {
    "op1_html_line_blocks": _ARTICLE,
    "op4_licence_digests": licences.oracle(),
    "op10_exact_dedup": """
        WITH t AS (SELECT doc_id, coalesce(text, '') AS text FROM documents)
        SELECT doc_id, max(doc_id) OVER w AS keep_id, count(*) OVER w AS group_size,
               doc_id = max(doc_id) OVER w AS kept, sha256(text) AS text_sha256
        FROM t WINDOW w AS (PARTITION BY text)
    """,
}
