"""The registered queries of this subpackage: each applies one operator to its whole table."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from congraph.llm.best_fit import pack_documents
from congraph.llm.bitpack import read_packed, write_packed
from congraph.llm.common import documents
from congraph.llm.exact_dedup import exact_classes
from congraph.llm.html_extract import extract_pages
from congraph.llm.kd_shards import shard_documents
from congraph.llm.line_dedup import dedup_lines
from congraph.llm.merkle import fingerprints
from congraph.llm.ngram_join import near_components
from congraph.llm.sentencepiece_viterbi import encode_digests
from congraph.llm.toxicity import score_toxicity


def op1_kd_shards(spark: SparkSession, sf_dir: str) -> DataFrame:
    return shard_documents(documents(spark, sf_dir), leaves=8)


def op2_ngram_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_components(documents(spark, sf_dir), percent=80, width=5).select("doc_id", "n_shingles", "component_id")


def op3_sentencepiece(spark: SparkSession, sf_dir: str) -> DataFrame:
    return encode_digests(documents(spark, sf_dir))


def op4_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    return score_toxicity(documents(spark, sf_dir), spark.read.parquet(f"{sf_dir}/labels.parquet"))


def op5_merkle(spark: SparkSession, sf_dir: str) -> DataFrame:
    return fingerprints(documents(spark, sf_dir))


def op6_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return dedup_lines(documents(spark, sf_dir))


def op7_html_main_text(spark: SparkSession, sf_dir: str) -> DataFrame:
    return extract_pages(spark.read.parquet(f"{sf_dir}/pages.parquet"))


def op8_exact_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return exact_classes(documents(spark, sf_dir))


def op9_packed_ids(spark: SparkSession, sf_dir: str) -> DataFrame:
    folder, manifest = write_packed(documents(spark, sf_dir))
    return read_packed(spark, folder, manifest)


def op10_best_fit(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pack_documents(documents(spark, sf_dir))


QUERIES = {f.__name__: f for f in (op1_kd_shards, op2_ngram_join, op3_sentencepiece, op4_toxicity, op5_merkle, op6_line_dedup, op7_html_main_text, op8_exact_dedup, op9_packed_ids, op10_best_fit)}

_NORM = "regexp_replace(coalesce(text, ''), '[\\x20\\x09-\\x0D]+', ' ', 'g')"

_LETTERS = "'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'"
_WORDS = "list_filter(string_split_regex({}, '[\\x20\\x09-\\x0D]+'), lambda x: x <> '')"

ORACLES = {
    "op2_ngram_join": f"""
        WITH RECURSIVE w AS (SELECT doc_id, {_WORDS.format(f"translate(coalesce(text, ''), {_LETTERS})")} AS ws FROM documents),
        s AS (SELECT DISTINCT doc_id, CASE WHEN len(ws) < 5 THEN array_to_string(ws, ' ') ELSE array_to_string(ws[i:i + 4], ' ') END AS g
              FROM (SELECT doc_id, ws, unnest(range(1, greatest(len(ws) - 4, 1) + 1)) AS i FROM w WHERE len(ws) > 0)),
        n AS (SELECT doc_id, count(*) AS n FROM s GROUP BY 1),
        common AS (SELECT a.doc_id AS a, b.doc_id AS b, count(*) AS k FROM s a JOIN s b ON a.g = b.g AND a.doc_id < b.doc_id GROUP BY ALL),
        link AS (SELECT a, b FROM common JOIN n x ON a = x.doc_id JOIN n y ON b = y.doc_id WHERE 100 * k >= 80 * (x.n + y.n - k)),
        both_ways AS (SELECT a, b FROM link UNION ALL SELECT b, a FROM link),
        reach AS (SELECT doc_id AS d, doc_id AS r FROM documents UNION SELECT reach.d, both_ways.b FROM reach JOIN both_ways ON reach.r = both_ways.a)
        SELECT doc_id, coalesce(n.n, 0) AS n_shingles, c.component_id
        FROM documents LEFT JOIN n USING (doc_id) JOIN (SELECT d, min(r) AS component_id FROM reach GROUP BY 1) c ON c.d = doc_id""",
    "op6_line_dedup": f"""
        WITH l AS (SELECT doc_id, i, lines[i] AS line FROM (SELECT doc_id, lines, unnest(range(1, len(lines) + 1)) AS i
                   FROM (SELECT doc_id, string_split(coalesce(text, ''), chr(10)) AS lines FROM documents))),
        t AS (SELECT doc_id, i, line, list_sort(list_distinct({_WORDS.format("lower(line)")})) AS ws FROM l),
        c AS (SELECT ws, min((doc_id, i)) AS first, len(ws) AS n, row_number() OVER () AS k FROM t WHERE len(ws) > 0 GROUP BY ws),
        word AS (SELECT k, n, unnest(ws) AS w FROM c),
        pair AS (SELECT a.k AS a, b.k AS b, a.n AS na, b.n AS nb, count(*) AS m FROM word a JOIN word b
                 ON a.w = b.w AND a.k < b.k AND 100 * a.n >= 80 * b.n AND 100 * b.n >= 80 * a.n GROUP BY ALL),
        hit AS (SELECT DISTINCT CASE WHEN x.first < y.first THEN y.k ELSE x.k END AS k FROM pair JOIN c x ON a = x.k JOIN c y ON b = y.k
                WHERE 100 * m >= 80 * (na + nb - m)),
        j AS (SELECT t.doc_id, t.i, t.line, coalesce(c.first <> (t.doc_id, t.i) OR hit.k IS NOT NULL, false) AS gone
              FROM t LEFT JOIN c ON t.ws = c.ws LEFT JOIN hit ON c.k = hit.k)
        SELECT doc_id, count(*) AS n_lines, count(*) FILTER (gone) AS n_removed,
               coalesce(string_agg(line, chr(10) ORDER BY i) FILTER (NOT gone), '') AS text FROM j GROUP BY 1""",
    "op8_exact_dedup": f"""
        WITH t AS (SELECT doc_id, {_NORM} AS x FROM documents)
        SELECT doc_id, min(doc_id) OVER (PARTITION BY x) AS keep_id, count(*) OVER (PARTITION BY x) AS group_size,
               doc_id = min(doc_id) OVER (PARTITION BY x) AS kept, sha256(x) AS text_sha256
        FROM t""",
}
