"""The registered queries of this subpackage: each applies one operator to its whole table."""

from __future__ import annotations

import os
import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import decontam, embeddup, langid, linededup, minhash, mixing, pii, quality, tokencounts, toxicity
from .common import discard, fold, shared_dir, stored, table

#: Folder of the public vocabularies.
TOKENIZERS = os.environ.get("CHARTREL_TOKENIZERS", "/opt/tokenizers")


def op7_mixing_to_targets(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mixing.taken_by_document(*mixing.mix_sources(mixing.sized(table(spark, sf_dir, "documents", "doc_id", "source", "text"))))


def op5_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    return langid.identify(table(spark, sf_dir, "documents", "doc_id", "text", "lang"))


def op6_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    return toxicity.score(table(spark, sf_dir, "documents", "doc_id", "text"), table(spark, sf_dir, "labels", "doc_id", "toxic"))


def op1_personal_data(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pii.personal_data(table(spark, sf_dir, "documents", "doc_id", "text"))


def op2_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All documents by words and by the byte-level vocabulary, one batch each.

    Further batches take the words of every fifth document off, put them back by a revision from nothing and an insert of none,
    and replay the first batch, which changes nothing; the pending deltas are merged into the totals on the way.
    """
    docs = table(spark, sf_dir, "documents", "doc_id", "source", "lang", "text")
    rollup = tokencounts.Rollup(spark, f"{shared_dir(spark)}/token-rollup-{uuid.uuid4().hex}", every=3)
    words = stored(tokencounts.words(docs).withColumn("part", fold("doc_id", 5)), "word-counts")
    bpe = tokencounts.counted(docs, f"{TOKENIZERS}/byte_bpe_50k.tiktoken")
    fifth, none = words.filter("part = 0"), F.lit(None).cast("long")

    def commit(batch: str, rows: DataFrame, name: str, op: str) -> None:
        rollup.apply(batch, tokencounts.deltas(rows.select("source", "lang", (none if op == "insert-empty" else F.col("tokens")).alias("tokens"), none.alias("old_tokens"), F.lit(op.removesuffix("-empty")).alias("op")), name))

    for batch, rows, name, op in (
        ("words", words, "words", "insert"), ("bpe", bpe, "byte_bpe_50k", "insert"), ("words-off", fifth, "words", "delete"),
        ("words-named", fifth, "words", "insert-empty"), ("words-back", fifth, "words", "revise"), ("words", words, "words", "insert"),
    ):
        commit(batch, rows, name, op)
    discard(words)
    return rollup.totals()


def op3_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    return quality.classify(table(spark, sf_dir, "documents", "doc_id", "text"))


def op4_minhash_neardup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return minhash.classes(table(spark, sf_dir, "documents", "doc_id", "text"))


def op8_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return linededup.dedup_lines(table(spark, sf_dir, "documents", "doc_id", "text"), min_tokens=1)


def op9_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    return decontam.matches(table(spark, sf_dir, "documents", "doc_id", "text"), table(spark, sf_dir, "benchmark", "item_id", "text"))


def op10_embedding_neardup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return embeddup.near_duplicates(table(spark, sf_dir, "embeddings", "vec_id", "embedding"))


_ALL = (
    op1_personal_data, op2_token_counts, op3_quality, op4_minhash_neardup, op5_language_id, op6_toxicity, op7_mixing_to_targets, op8_line_dedup,
    op9_decontamination, op10_embedding_neardup,
)
QUERIES = {f.__name__: f for f in _ALL}

_OPEN = ", ".join(f"[to_json([n, {r}]), to_json(t[1:3 + (n - 3) * {r} // 4]), to_json(t[4 + (n - 3) * {r + 1} // 4:])]" for r in range(linededup.RUNS))

#: DuckDB SQL by query name; what it states is the definition, compared over all pairs of lines or vectors.
ORACLES: dict[str, str] = {
    "op8_line_dedup": f"""
        with row as (select row_number() over () as r, doc_id, text from documents),
        cut as (select r, doc_id, unnest(string_split(text, chr(10))) line, generate_subscripts(string_split(text, chr(10)), 1) as pos from row where doc_id is not null and text is not null),
        masked as (select *, regexp_replace(line, '[^\\x20\\x09-\\x0D]*[0-9][^\\x20\\x09-\\x0D]*', '<*>', 'g') as m, list_filter(string_split(line, ' '), lambda x: x <> '') as own
                   from cut where regexp_matches(line, '[^\\x20\\x09-\\x0D]')),
        token as (select doc_id, pos, case when regexp_matches(line, '[0-9]') and len(own) < {linededup.MIN_TOKENS} and (not regexp_matches(replace(m, '<*>', ''), '\\p{{L}}')
                    or octet_length(encode(line)) - octet_length(encode(replace(m, '<*>', ''))) > {linededup.HIDDEN}) then own else list_filter(string_split(m, ' '), lambda x: x <> '') end as t from masked),
        sized as (select *, len(t) as n from token),
        keys as (select doc_id, pos, unnest(case when n >= {linededup.LEADING + linededup.RUNS} then [[to_json(t)], {_OPEN}] else [[to_json(t)]] end) as key from sized),
        first as (select key, min(doc_id) as first from keys group by key),
        gone as (select distinct doc_id, pos from keys join first using (key) where doc_id > first),
        kept as (select c.r, c.pos, c.line, g.pos is not null as dropped from cut c left join gone g on c.doc_id = g.doc_id and c.pos = g.pos),
        text as (select r, coalesce(string_agg(line, chr(10) order by pos) filter (where not dropped), '') as text, count(*) filter (where dropped) as dropped_lines from kept group by r)
        select d.doc_id, case when coalesce(k.dropped_lines, 0) = 0 then d.text else k.text end as text, coalesce(k.dropped_lines, 0)::bigint as dropped_lines
        from row d left join text k on d.r = k.r""",
    "op10_embedding_neardup": f"""
        with recursive sound as (select row_number() over () as i, vec_id, embedding::double[] as e from embeddings
                       where vec_id is not null and embedding is not null and len(list_filter(embedding, lambda x: x is null or not isfinite(x))) = 0 and len(list_filter(embedding, lambda x: x <> 0)) > 0),
        link as (select a.i as a, b.i as b from sound a join sound b on a.i <> b.i and len(a.e) = len(b.e) and list_cosine_similarity(a.e, b.e) >= {embeddup.COSINE}),
        reach(a, b) as (select i, i from sound union select reach.a, link.b from reach join link on reach.b = link.a),
        least as (select a, min(s.vec_id) as component_id from reach join sound s on reach.b = s.i group by a),
        many as (select a, count(*) as n from link group by a),
        found as (select s.vec_id, coalesce(m.n, 0)::bigint as n_links, l.component_id from sound s join least l on l.a = s.i left join many m on m.a = s.i)
        select vec_id, n_links, component_id, vec_id = component_id as kept from found
        union all select vec_id, 0::bigint, vec_id, vec_id is not null from embeddings
        where vec_id is null or embedding is null or len(list_filter(embedding, lambda x: x is null or not isfinite(x))) > 0 or len(list_filter(embedding, lambda x: x <> 0)) = 0""",
}
