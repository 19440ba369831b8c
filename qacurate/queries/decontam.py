"""Leak search and removal."""

from __future__ import annotations

from pyspark.sql import functions as F

from qacurate.functions.text import ngrams, tokens
from qacurate.operators import decontam as D
from qacurate.operators import knn
from qacurate.operators.ngram import ngram_decontaminate
from qacurate.queries.common import docs, words_sql
from qacurate.registry import query, read


def items(spark, d):
    return read(spark, d, "benchmark").select("item_id", "text", tokens("text").alias("words"))


def questions(spark, d):
    return D.window_questions(docs(spark, d), "doc_id")


_POOL = "select 'set_' || (item_id % 3) as benchmark, item_id, text from benchmark"


@query("benchmark_pool", f"select benchmark, count(*) as n, sum(length(text))::bigint as chars from ({_POOL}) group by benchmark")
def benchmark_pool(spark, d):
    b = read(spark, d, "benchmark")
    pool = D.benchmark_pool(*[(f"set_{k}", b.where(F.col("item_id") % 3 == k)) for k in range(3)])
    return pool.groupBy("benchmark").agg(F.count(F.lit(1)).alias("n"), F.sum(F.length("text")).cast("long").alias("chars"))


def _sparse_sql(table: str, key: str) -> str:
    return f"""select {key}, bucket, sum(s)::bigint as weight from (
  select {key}, ('0x' || substr(md5(w), 1, 3))::int // 16 as bucket, case when ('0x' || substr(md5(w), 1, 3))::int % 16 >= 8 then 1 else -1 end as s
  from (select {key}, unnest(words) as w from {table})) group by {key}, bucket having sum(s) <> 0"""


_ITEMS = f"items as (select item_id, {words_sql('text')} as words from benchmark)"
_WINDOWS = f"""w as (select doc_id, {words_sql('text')} as w from documents),
questions as (select doc_id, doc_id || ':' || i as id, list_slice(w, i * 16 + 1, i * 16 + 32) as words
  from w, unnest(range(0, case when len(w) = 0 then 0 else greatest(ceil((len(w) - 32) / 16.0) + 1, 1)::bigint end)) as u(i))"""
_TOPK = f"""q as ({_sparse_sql('questions', 'id')}), m as ({_sparse_sql('items', 'item_id')}),
nq as (select id, sum(weight * weight) as nq from q group by id), nm as (select item_id, sum(weight * weight) as nm from m group by item_id),
dots as (select id, item_id, sum(q.weight * m.weight) as dot from q join m using (bucket) group by all),
scored as (select id, item_id, round(dot::double / sqrt((nq * nm)::double), 6) as similarity from dots join nq using (id) join nm using (item_id)),
topk as (select id, item_id, similarity, row_number() over (partition by id order by similarity desc, item_id) as rank from scored qualify rank <= 5)"""
_JUDGED = """pairs as (select t.id, t.item_id, t.rank, q.doc_id, list_distinct(q.words) as a, list_distinct(i.words) as b from topk t join questions q using (id) join items i using (item_id)),
judged as (select id, item_id, rank, doc_id, len(a) >= 8 and len(b) >= 8 and len(list_intersect(a, b))::double / least(len(a), len(b)) >= 0.7 as paraphrase from pairs)"""
_ALL = f"with {_ITEMS}, {_WINDOWS}, {_TOPK}, {_JUDGED}"
_EVIDENCE = "(select doc_id, arg_min(item_id, rank * 1000000000 + item_id) as item_id, min(rank)::int as rank from judged where paraphrase group by doc_id)"


@query("text_embeddings", f"with {_ITEMS} {_sparse_sql('items', 'item_id')}")
def text_embeddings(spark, d):
    return D.sparse_embeddings(items(spark, d), ["item_id"])


_VEC = "select vec_id as id, embedding::double[] as v from embeddings where vec_id % 5 {} 0"
_EXACT = f"""with q as ({_VEC.format('<>')}), m as ({_VEC.format('=')}),
s as (select q.id, m.id as item_id, round(list_dot_product(q.v, m.v) / (sqrt(list_dot_product(q.v, q.v)) * sqrt(list_dot_product(m.v, m.v))), 6) as similarity from q, m),
t as (select *, row_number() over (partition by id order by similarity desc, item_id) as rank from s)
select id, item_id, rank::int as rank, similarity from t where rank <= 5"""


def _vectors(spark, d):
    e = read(spark, d, "embeddings")
    q = e.where("vec_id % 5 <> 0").select(F.col("vec_id").alias("id"), F.col("embedding").alias("vec"))
    return q, e.where("vec_id % 5 = 0").select(F.col("vec_id").alias("item_id"), F.col("embedding").alias("vec"))


for _name, _fn in (("topk_exact", knn.topk_exact), ("topk_block", knn.topk_block), ("topk_sharded", knn.topk_sharded)):
    query(_name, _EXACT)(lambda spark, d, f=_fn: f(*_vectors(spark, d)))


@query("topk_label_agreement", f"with t as ({_EXACT}) select count(*) as n, count_if(a.label = b.label) as n_same from t join embeddings a on a.vec_id = t.id join embeddings b on b.vec_id = t.item_id")
def topk_label_agreement(spark, d):
    e = read(spark, d, "embeddings")
    found = knn.topk_block(*_vectors(spark, d))
    a, b = e.select(F.col("vec_id").alias("id"), F.col("label").alias("la")), e.select(F.col("vec_id").alias("item_id"), F.col("label").alias("lb"))
    return found.join(a, "id").join(b, "item_id").agg(F.count(F.lit(1)).alias("n"), F.count_if(F.col("la") == F.col("lb")).alias("n_same"))


_EVERY = """with q as (select vec_id as id, embedding::double[] as v from embeddings where vec_id % 50 = 0), m as (select vec_id as id, embedding::double[] as v from embeddings),
s as (select q.id, m.id as item_id, round(list_dot_product(q.v, m.v) / (sqrt(list_dot_product(q.v, q.v)) * sqrt(list_dot_product(m.v, m.v))), 6) as similarity from q join m on q.id <> m.id),
t as (select *, row_number() over (partition by id order by similarity desc, item_id) as rank from s)
select id, item_id, rank::int as rank, similarity from t where rank <= 5"""


def _every_row(spark, d):
    """Every fiftieth row as a question, all rows as items."""
    e = read(spark, d, "embeddings")
    return e.where("vec_id % 50 = 0").select(F.col("vec_id").alias("id"), F.col("embedding").alias("vec")), e.select(F.col("vec_id").alias("item_id"), F.col("embedding").alias("vec"))


def _others(found):
    """The five best of six without the question itself."""
    return knn._ranked(found.where("id <> item_id"), 5)


@query("topk_every_row", _EVERY)
def topk_every_row(spark, d):
    q, m = _every_row(spark, d)
    large = m.limit(knn.BROADCAST_ROWS + 1).count() > knn.BROADCAST_ROWS
    return _others((knn.topk_sharded if large else knn.topk_exact)(q, m, 6))


@query("topk_embeddings", _EVERY)
def topk_embeddings(spark, d):
    """The same by shards of items, the form for item tables of any size."""
    q, m = _every_row(spark, d)
    return _others(knn.topk_sharded(q, m, 6))


@query("topk_ivf")
def topk_ivf(spark, d):
    return _others(knn.topk_ivf(*_every_row(spark, d), 6))


@query("topk_lsh")
def topk_lsh(spark, d):
    return _others(knn.topk_lsh(*_every_row(spark, d), 6))


@query("topk_lsh_recall")
def topk_lsh_recall(spark, d):
    return knn.recall_at_k(_others(knn.topk_lsh(*_every_row(spark, d), 6)), topk_every_row(spark, d))


@query("topk_ivf_recall")
def topk_ivf_recall(spark, d):
    return knn.recall_at_k(_others(knn.topk_ivf(*_every_row(spark, d), 6)), topk_every_row(spark, d))


@query("topk_text", f"with {_ITEMS}, {_WINDOWS}, {_TOPK} select id, item_id, rank::int as rank, similarity from topk")
def topk_text(spark, d):
    return D.topk_text(questions(spark, d), items(spark, d)).select("id", "item_id", "rank", "similarity")


def _judged(spark, d):
    return D.judge(D.judged_pairs(questions(spark, d), items(spark, d), search="text"))


@query("judge_pairs", f"{_ALL} select rank::int as rank, count(*) as n from judged group by rank")
def judge_pairs(spark, d):
    return _judged(spark, d).groupBy("rank").agg(F.count(F.lit(1)).alias("n"))


@query("paraphrase_judge", f"{_ALL} select id, item_id, rank::int as rank from judged where paraphrase")
def paraphrase_judge(spark, d):
    return D.judge(D.judged_pairs(questions(spark, d), items(spark, d))).where("paraphrase").select("id", "item_id", "rank")


@query("decontaminate", f"{_ALL} select * from {_EVIDENCE}")
def decontaminate(spark, d):
    return D.decontaminate(questions(spark, d), items(spark, d))


@query("decontaminate_text", f"{_ALL} select * from {_EVIDENCE}")
def decontaminate_text(spark, d):
    """The same with sparse vectors and inverted lists by bucket instead of matrices."""
    return D.decontaminate(questions(spark, d), items(spark, d), search="text")


@query("decontaminate_cascade", f"{_ALL} select doc_id, rank from {_EVIDENCE}")
def decontaminate_cascade(spark, d):
    return D.decontaminate(questions(spark, d), items(spark, d), cascade=True).select("doc_id", "rank")


def _gram_sql(n: int, keep: str = "select distinct id from q join b using (g)") -> str:
    gram = f"case when len(w) = 0 then [] else list_distinct(list_transform(range(0, greatest(len(w) - {n - 1}, 1)), lambda i: array_to_string(list_slice(w, i + 1, i + {n}), ' '))) end"
    return f"""with b as (select distinct unnest({gram}) as g from (select {words_sql('text')} as w from benchmark)),
q as (select doc_id as id, unnest({gram}) as g from (select doc_id, {words_sql('text')} as w from documents))
{keep}"""


for _n in (5, 8, 13):
    query(f"decontam_ngram_{_n}", _gram_sql(_n))(lambda spark, d, n=_n: ngram_decontaminate(docs(spark, d).select(F.col("doc_id").alias("id"), "text"), read(spark, d, "benchmark"), n))


_SHARE = "select id from (select id, count(*) as n, count(b.g) as hit from q left join b on q.g = b.g group by id) where hit > 0 and hit >= 0.1::double * n"


@query("decontam_ngram_share", _gram_sql(5, _SHARE))
def decontam_ngram_share(spark, d):
    return ngram_decontaminate(docs(spark, d).select(F.col("doc_id").alias("id"), "text"), read(spark, d, "benchmark"), 5, 0.1)


@query("decontam_embedding", f"with {_ITEMS}, {_WINDOWS}, {_TOPK} select distinct doc_id from topk join questions using (id) where rank = 1 and similarity >= 0.72")
def decontam_embedding(spark, d):
    return D.embedding_decontaminate(questions(spark, d), items(spark, d))


@query("leakage_report", f"""{_ALL}, r as (select distinct doc_id, 1 as leak from judged where paraphrase)
select coalesce(lang, 'total') as lang, count(leak) as n_leaked, count(*) as n, round(100.0 * count(leak) / count(*), 4)::double as share from documents left join r using (doc_id) group by rollup (lang)""")
def leakage_report(spark, d):
    removed = D.decontaminate(questions(spark, d), items(spark, d))
    return D.leakage_report(removed, docs(spark, d).select("doc_id", "lang"), "lang")


@query("detector_recall")
def detector_recall(spark, d):
    return D.detector_recall(items(spark, d).select("item_id", "words"))


@query("shared_ngrams", f"with t as ({_gram_sql(13)}) select count(*) as n from t")
def shared_ngrams(spark, d):
    grams = read(spark, d, "benchmark").select(F.explode(ngrams(tokens("text"), 13)).alias("g")).distinct()
    q = docs(spark, d).select("doc_id", F.explode(ngrams(tokens("text"), 13)).alias("g"))
    return q.join(grams, "g", "left_semi").select("doc_id").distinct().agg(F.count(F.lit(1)).alias("n"))
