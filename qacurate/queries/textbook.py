"""Collection, chunking and extraction."""

from __future__ import annotations

from pyspark.sql import functions as F

from qacurate.functions.text import n_tokens
from qacurate.operators import extract, ingest
from qacurate.queries.common import BOOKS_SQL, SUBJECT_SQL, TURNS_SQL, books, chunks, docs, labels, spaced_sql, turns, with_sql, words_sql
from qacurate.registry import query, read


@query("restricted_filter", f"with books as ({BOOKS_SQL}) select book_id, source from books where not restricted")
def restricted_filter(spark, d):
    return ingest.drop_restricted(books(spark, d)).select("book_id", "source")


@query("subject_assign", f"select doc_id as book_id, array_to_string({SUBJECT_SQL}, '+') as subjects from documents")
def subject_assign(spark, d):
    return books(spark, d).select("book_id", F.array_join("subjects", "+").alias("subjects"))


@query("level_gate", "select d.doc_id as book_id, 'university' as level from documents d left join (select doc_id, min(quality) as q from labels group by doc_id) l using (doc_id) where length(text) >= 200 and coalesce(q, 1) = 1")
def level_gate(spark, d):
    return ingest.level_gate(books(spark, d), labels(spark, d)).select("book_id", "level")


def _page_sql() -> str:
    text = "coalesce(html, '')"
    for cut in ingest.PAGE_CUTS:
        text = f"regexp_replace({text}, '{cut}', ' ', 'g')"
    for entity, mark in ingest.ENTITIES:
        text = "replace({}, '{}', '{}')".format(text, entity, mark.replace("'", "''"))
    return rf"select page_id, trim(regexp_replace({text}, '[ \t\r\n]+', ' ', 'g')) as text from pages"


@query("digitise_pages", _page_sql())
def digitise_pages(spark, d):
    return ingest.digitise(read(spark, d, "pages")).select("page_id", "text")


@query("token_counts", rf"select doc_id, len({words_sql('text')})::bigint as n_words, len({spaced_sql('text')})::bigint as n_spaced, length(coalesce(text, ''))::bigint as n_chars from documents")
def token_counts(spark, d):
    return docs(spark, d).select("doc_id", n_tokens("text").cast("long").alias("n_words"), n_tokens("text", "space").cast("long").alias("n_spaced"), F.length(F.coalesce("text", F.lit(""))).cast("long").alias("n_chars"))


def _chunk_query(name: str, size: int, overlap: int) -> None:
    sql = f"{with_sql(size, overlap)} select book_id, chunk_no, len(part)::bigint as n_tokens, md5(array_to_string(part, '')) as digest from chunks"

    @query(name, sql)
    def run(spark, d):
        return chunks(spark, d, size, overlap).select("book_id", "chunk_no", F.col("n_tokens").cast("long").alias("n_tokens"), F.md5("text").alias("digest"))


_chunk_query("chunk_4096", 4096, 0)
_chunk_query("chunk_512", 512, 0)
_chunk_query("chunk_overlap", 512, 64)


def _extract_query(name: str, table: str, pick) -> None:
    @query(name, f"{with_sql()} select qid, standard, md5(question) as question, md5(answer) as answer from {table}")
    def run(spark, d):
        return pick(chunks(spark, d)).select("qid", "standard", F.md5("question").alias("question"), F.md5("answer").alias("answer"))


_extract_query("extract_high", "high", lambda c: extract.extract_pairs(c, "high"))
_extract_query("extract_low", "low", lambda c: extract.extract_pairs(c, "low"))
_extract_query("extract_dual", "pairs", extract.extract_dual)

STATS_SQL = f"""{with_sql()}, b as (select book_id, unnest(list_concat(subjects, ['total'])) as subject from books),
v as (select book_id, chunk_no, count_if(standard = 'high') as high, count_if(standard = 'low') as low from pairs group by all),
p as (select book_id, count(*) as valid, sum(high) as high, sum(low) as low from v group by book_id),
c as (select book_id, count(*) as n from chunks group by book_id)
select subject, count(*)::bigint as n_books, coalesce(sum(n), 0)::bigint as n_chunks, coalesce(sum(valid), 0)::bigint as n_valid_chunks,
  coalesce(sum(high), 0)::bigint as n_pairs_high, coalesce(sum(low), 0)::bigint as n_pairs_low
from b left join c using (book_id) left join p using (book_id) group by subject"""


def stats(spark, d):
    c = chunks(spark, d)
    return extract.extraction_stats(books(spark, d), c, extract.extract_dual(c))


@query("extraction_stats", STATS_SQL)
def extraction_stats(spark, d):
    return stats(spark, d)


@query("valid_chunk_rate", f"select subject, round(100.0 * n_valid_chunks / nullif(n_chunks, 0), 4) as valid_rate, round((n_pairs_high + n_pairs_low)::double / nullif(n_valid_chunks, 0), 4) as pairs_per_valid from ({STATS_SQL})")
def valid_chunk_rate(spark, d):
    return extract.valid_chunk_rate(stats(spark, d))


@query("qa_from_turns", TURNS_SQL)
def qa_from_turns(spark, d):
    return turns(spark, d)


@query("synth_questions", rf"{with_sql()} select book_id || ':' || chunk_no || ':synth' as qid, 'What follows from: ' || array_to_string(list_slice(regexp_split_to_array(trim(array_to_string(part, '')), '[ \n]+'), 1, 8), ' ') || '?' as question from chunks")
def synth_questions(spark, d):
    return extract.synthesise_questions(chunks(spark, d)).select("qid", "question")
