"""Tables derived from the given ones, as DataFrames and as the SQL the oracles share."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from qacurate.functions.text import shingles
from qacurate.operators import ingest
from qacurate.registry import read

W = r"[\p{L}\p{N}]+"


def words_sql(c: str) -> str:
    return f"regexp_extract_all(lower(coalesce({c}, '')), '{W}')"


def spaced_sql(c: str) -> str:
    return rf"regexp_extract_all(coalesce({c}, ''), '[^ \t\n\r]+')"


def docs(spark: SparkSession, d: str) -> DataFrame:
    return read(spark, d, "documents")


def labels(spark: SparkSession, d: str) -> DataFrame:
    return read(spark, d, "labels")


def books(spark: SparkSession, d: str) -> DataFrame:
    return ingest.assign_subjects(ingest.books(docs(spark, d)))


def chunks(spark: SparkSession, d: str, size: int = 4096, overlap: int = 0) -> DataFrame:
    return ingest.chunk(books(spark, d), size, overlap)


#: Planted cases of the recipes: one book per benchmark item that asks it, copies of every tenth document with a word
#: added to each line, and books that refer to what they do not hold. Ids of each kind have a range of their own.
_FOLLOWS = "The answer follows because the statement above holds and so it is known to all."


def recipe_docs(spark: SparkSession, d: str) -> DataFrame:
    """The documents and the planted cases: (doc_id, text, lang, source)."""
    t = docs(spark, d).select("doc_id", "text", "lang", "source")
    asked = F.concat(F.regexp_replace("text", "[\\r\\n]+", " "), F.lit("\n" + _FOLLOWS))
    leaks = read(spark, d, "benchmark").select((F.lit(1_000_000_000) + F.col("item_id")).alias("doc_id"), asked.alias("text"), F.lit("en").alias("lang"), F.concat(F.lit("src"), (F.col("item_id") % 7).cast("string")).alias("source"))
    copies = t.where("doc_id % 10 = 0").select((F.lit(2_000_000_000) + F.col("doc_id")).alias("doc_id"), F.regexp_replace("text", "\n", " again\n").alias("text"), "lang", "source")
    tag = lambda x: F.md5(F.concat(F.lit(x), F.col("doc_id").cast("string")))
    poor = F.concat(F.lit("Consider the case "), tag("c"), F.lit(" of the kind "), tag("k"), F.lit(" and say what it means\nappendix 4 holds the whole proof of case "), tag("p"), F.lit(" and nothing more"))
    defects = t.where("doc_id % 20 = 3").select((F.lit(3_000_000_000) + F.col("doc_id")).alias("doc_id"), poor.alias("text"), "lang", "source")
    return t.unionByName(leaks).unionByName(copies).unionByName(defects)


def recipe_books(spark: SparkSession, d: str) -> DataFrame:
    return ingest.assign_subjects(ingest.books(recipe_docs(spark, d)))


RECIPE_DOCS_SQL = rf"""select doc_id, text, lang, source from documents
union all select 1000000000 + item_id, regexp_replace(text, '[\r\n]+', ' ', 'g') || chr(10) || '{_FOLLOWS}', 'en', 'src' || (item_id % 7) from benchmark
union all select 2000000000 + doc_id, replace(text, chr(10), ' again' || chr(10)), lang, source from documents where doc_id % 10 = 0
union all select 3000000000 + doc_id, 'Consider the case ' || md5('c' || doc_id) || ' of the kind ' || md5('k' || doc_id) || ' and say what it means' || chr(10) || 'appendix 4 holds the whole proof of case ' || md5('p' || doc_id) || ' and nothing more', lang, source from documents where doc_id % 20 = 3"""


def turns(spark: SparkSession, d: str) -> DataFrame:
    return ingest.pairs_from_turns(read(spark, d, "conversations"))


def word_sets(spark: SparkSession, d: str) -> DataFrame:
    """Word sets of documents, one of each group of equal word sequences."""
    from qacurate.operators.minhash import exact_dedup

    table = docs(spark, d)
    kept = exact_dedup(table, "doc_id", "text").where("id = keep").select("id")
    return table.select(F.col("doc_id").alias("id"), shingles("text").alias("set")).join(kept, "id", "left_semi")


SUBJECT_SQL = "case (regexp_extract(source, '([0-9]+)', 1))::int % 7 " + " ".join(f"when {i} then {list(s)!r}" for i, s in enumerate(ingest.SUBJECTS)) + " end"
BOOKS_SQL = f"select doc_id as book_id, text, source, lang, coalesce(regexp_matches(lower(text), '{ingest.RESTRICTED}'), false) as restricted, {SUBJECT_SQL} as subjects from documents"


def chunks_sql(size: int = 4096, overlap: int = 0) -> str:
    step = size - overlap
    return rf"""select book_id, subjects, i::int as chunk_no, list_slice(w, i * {step} + 1, i * {step} + {size}) as part
from (select book_id, subjects, regexp_extract_all(coalesce(text, ''), '[ \t\n\r]*[^ \t\n\r]+') as w from books) t,
  unnest(range(0, case when len(w) = 0 then 0 else greatest(ceil((len(w) - {overlap}) / {step}.0), 1)::bigint end)) as u(i)"""


def pairs_sql(name: str, q: int, a: int, s: int, lines: int) -> str:
    return rf"""select book_id || ':' || chunk_no || ':' || i || ':{name}' as qid, book_id, chunk_no, i::int as line, '{name}' as standard, ls[i + 1] as question,
    array_to_string(list_slice(ls, i + 2, i + 1 + {lines}), chr(10)) as answer
from (select book_id, chunk_no, string_split(array_to_string(part, ''), chr(10)) as ls from chunks) t, unnest(range(0, len(ls))) as u(i)
where len({spaced_sql('ls[i + 1]')}) >= greatest(6, {q}) and len({spaced_sql('ls[i + 2]')}) >= 6
  and len({spaced_sql("array_to_string(list_slice(ls, i + 2, i + 1 + " + str(lines) + "), chr(10))")}) >= {a}
  and len(regexp_extract_all(array_to_string(list_slice(ls, i + 2, i + 1 + {lines}), chr(10)), '[.!?]( |\n|$)')) >= {s}"""


HIGH_SQL, LOW_SQL = pairs_sql("high", 40, 250, 20, 5), pairs_sql("low", 6, 6, 0, 1)


def with_sql(size: int = 4096, overlap: int = 0, docs_sql: str | None = None) -> str:
    """The chain of tables up to pairs, for the start of an oracle. docs_sql: other documents than the given ones."""
    head = "with " if docs_sql is None else f"with recursive book_docs as ({docs_sql}), "
    books_sql = BOOKS_SQL if docs_sql is None else BOOKS_SQL.replace("from documents", "from book_docs")
    return f"{head}books as ({books_sql}), chunks as ({chunks_sql(size, overlap)}), high as ({HIGH_SQL}), low as ({LOW_SQL}), pairs as (select * from high union all select * from low)"


TURNS_SQL = """select conv_id || ':' || turn as qid, conv_id, turn, text as question, answer from (
  select *, lead(role) over w as next_role, lead(text) over w as answer from conversations window w as (partition by conv_id order by turn)
) where role = 'user' and next_role = 'assistant'"""


def dedup_sql(table: str, p: str, scope: str | None = None) -> str:
    """Tables that end in {p}copies (id, keep) and {p}comp (node, component): MinHash deduplication of (id, text[, scope]).

    Pairs that share a band and are similar enough make the components.
    """
    from qacurate.operators import minhash as M

    signature = ", ".join(f"min((x * {a} + {b}) % {M.PRIME})" for a, b in M.coefficients())
    g = f", {scope}" if scope else ""
    same = f" and a.{scope} = b.{scope}" if scope else ""
    return f"""{p}k as (select id{g}, {words_sql('text')} as ws from {table}),
{p}x as (select ws{g}, min(id) as id from {p}k group by all),
{p}s as (select id{g}, list_distinct(ws) as s from {p}x where len(ws) > 0),
{p}h as (select id, (('0x' || substr(md5(w), 1, 8))::bigint & {M.PRIME}) % {M.PRIME} as x from (select id, unnest(s) as w from {p}s)),
{p}sig as (select id, [{signature}] as sig from {p}h group by id),
{p}b as (select id, i as band, array_to_string(list_slice(sig, i * 4 + 1, i * 4 + 4), ',') as key from {p}sig, unnest(range(0, 32)) as u(i)),
{p}c as (select distinct l.id as a, r.id as b from {p}b l join {p}b r on l.band = r.band and l.key = r.key and l.id < r.id),
{p}e as (select c.a, c.b from {p}c c join {p}s a on c.a = a.id join {p}s b on c.b = b.id{same}
  where len(list_intersect(a.s, b.s))::double / (len(a.s) + len(b.s) - len(list_intersect(a.s, b.s))) >= 0.6),
{p}sym as (select a, b from {p}e union all select b, a from {p}e),
{p}reach as (select a as node, b as other from {p}sym union select r.node, y.b from {p}reach r join {p}sym y on r.other = y.a),
{p}comp as (select node, least(node, min(other)) as component from {p}reach group by node),
{p}copies as (select k.id, x.id as keep from {p}k k join {p}x x on k.ws = x.ws{same.replace('a.', 'k.').replace('b.', 'x.')}),
{p}kept as (select c.id as qid from {p}copies c left join {p}comp m on c.keep = m.node where coalesce(m.component, c.keep) = c.id)"""


def leaks_sql(table: str, p: str) -> str:
    """Tables that end in {p}leaks (qid): questions of (qid, question) with a window that is judged a paraphrase of one of its five items."""

    def sparse(words: str, key: str) -> str:
        return f"""select {key}, bucket, sum(s)::bigint as weight from (
  select {key}, ('0x' || substr(md5(w), 1, 3))::int // 16 as bucket, case when ('0x' || substr(md5(w), 1, 3))::int % 16 >= 8 then 1 else -1 end as s
  from (select {key}, unnest(words) as w from {words})) group by {key}, bucket having sum(s) <> 0"""

    return f"""{p}items as (select item_id, {words_sql('text')} as words from benchmark),
{p}w as (select distinct qid, {words_sql('question')} as w from {table}),
{p}questions as (select qid, qid || ':' || i as id, list_slice(w, i * 16 + 1, i * 16 + 32) as words
  from {p}w, unnest(range(0, case when len(w) = 0 then 0 else greatest(ceil((len(w) - 32) / 16.0) + 1, 1)::bigint end)) as u(i)),
{p}q as ({sparse(p + 'questions', 'id')}), {p}m as ({sparse(p + 'items', 'item_id')}),
{p}nq as (select id, sum(weight * weight) as nq from {p}q group by id), {p}nm as (select item_id, sum(weight * weight) as nm from {p}m group by item_id),
{p}dots as (select id, item_id, sum(q.weight * m.weight) as dot from {p}q q join {p}m m using (bucket) group by all),
{p}scored as (select id, item_id, round(dot::double / sqrt((nq * nm)::double), 6) as similarity from {p}dots join {p}nq using (id) join {p}nm using (item_id)),
{p}topk as (select id, item_id, row_number() over (partition by id order by similarity desc, item_id) as rank from {p}scored qualify rank <= 5),
{p}sides as (select q.qid, list_distinct(q.words) as a, list_distinct(i.words) as b from {p}topk t join {p}questions q using (id) join {p}items i using (item_id)),
{p}leaks as (select distinct qid from {p}sides where len(a) >= 8 and len(b) >= 8 and len(list_intersect(a, b))::double / least(len(a), len(b)) >= 0.7)"""
