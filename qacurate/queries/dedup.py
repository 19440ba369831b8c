"""Question deduplication: exact, MinHash, keep-rules, exact joins, quality."""

from __future__ import annotations

from pyspark.sql import functions as F

from qacurate.functions.text import jaccard, shingles
from qacurate.operators import minhash as M
from qacurate.operators.graph import components
from qacurate.queries.common import docs, word_sets, words_sql
from qacurate.registry import query

_KEYED = f"select doc_id as id, source, length(text) as n, {words_sql('text')} as ws from documents"
#: Distinct texts with their word sets, and all pairs at or above the threshold.
_BASE = f"""with recursive k as ({_KEYED}), x as (select ws, min(id) as id, any_value(source) as source from k group by ws),
s as (select id, list_distinct(ws) as s from x),
p as (select a.id as a, b.id as b, len(list_intersect(a.s, b.s)) as shared, len(a.s) as na, len(b.s) as nb from s a join s b on a.id < b.id and least(len(a.s), len(b.s)) >= 0.6 * greatest(len(a.s), len(b.s)) and len(a.s) > 0),
e as (select a, b, shared::double / (na + nb - shared) as similarity from p where shared::double / (na + nb - shared) >= 0.6),
sym as (select a, b from e union all select b, a from e),
reach as (select a as node, b as other from sym union select r.node, sym.b from reach r join sym on r.other = sym.a),
comp as (select node, least(node, min(other)) as component from reach group by node)"""
_COPIES = "copies as (select k.id, x.id as keep from k join x using (ws))"


@query("dedup_exact", f"with k as ({_KEYED}), x as (select ws, min(id) as keep from k group by ws) select id, keep from k join x using (ws)")
def dedup_exact(spark, d):
    return M.exact_dedup(docs(spark, d), "doc_id", "text")


_GRAM = """list_distinct(list_transform(range(0, greatest(len(w) - 2, 1)), lambda i: array_to_string(list_slice(w, i + 1, i + 3), ' ')))"""


@query("shingle_stats", f"with t as (select doc_id, {words_sql('text')} as w from documents) select doc_id, len(list_distinct(w))::bigint as n_words, (case when len(w) = 0 then 0 else len({_GRAM}) end)::bigint as n_trigrams from t")
def shingle_stats(spark, d):
    return docs(spark, d).select("doc_id", F.size(shingles("text")).cast("long").alias("n_words"), F.size(shingles("text", 3)).cast("long").alias("n_trigrams"))


def _signature_sql(n: int = 8) -> str:
    parts = ", ".join(f"min((x * {a} + {b}) % {M.PRIME})" for a, b in M.coefficients()[:n])
    return f"""with k as (select doc_id as id, unnest(list_distinct({words_sql('text')})) as w from documents),
h as (select id, (('0x' || substr(md5(w), 1, 8))::bigint & {M.PRIME}) % {M.PRIME} as x from k)
select id, concat_ws(',', {parts}) as head from h group by id"""


@query("minhash_signature", _signature_sql())
def minhash_signature(spark, d):
    sets = docs(spark, d).select(F.col("doc_id").alias("id"), shingles("text").alias("set"))
    return M.minhash(sets).where("signature is not null").select("id", F.array_join(F.slice("signature", 1, 8), ",").alias("head"))


def _bands_sql(bands: int = 32, rows: int = 4) -> str:
    c = M.coefficients()
    signature = ", ".join(f"min((x * {a} + {b}) % {M.PRIME})" for a, b in c)
    return f"""with k as (select doc_id as id, unnest(list_distinct({words_sql('text')})) as w from documents),
h as (select id, (('0x' || substr(md5(w), 1, 8))::bigint & {M.PRIME}) % {M.PRIME} as x from k),
s as (select id, [{signature}] as sig from h group by id),
b as (select id, i as band, array_to_string(list_slice(sig, i * {rows} + 1, i * {rows} + {rows}), ',') as key from s, unnest(range(0, {bands})) as u(i)),
z as (select band, key, count(*) as n from b group by all)
select n as bucket_size, count(*) as n_buckets from z group by n"""


@query("lsh_band_sizes", _bands_sql())
def lsh_band_sizes(spark, d):
    sets = docs(spark, d).select(F.col("doc_id").alias("id"), shingles("text").alias("set"))
    sizes = M.lsh_bands(M.minhash(sets)).groupBy("band", "key").agg(F.count(F.lit(1)).alias("bucket_size"))
    return sizes.groupBy("bucket_size").agg(F.count(F.lit(1)).alias("n_buckets"))


def _edges(spark, d, **shape):
    return M.similar_edges(docs(spark, d), "doc_id", "text", **shape)


@query("lsh_pairs_verified", f"{_BASE} select a, b, round(similarity, 6) as similarity from e")
def lsh_pairs_verified(spark, d):
    return _edges(spark, d)[1].select("a", "b", F.round("similarity", 6).alias("similarity"))


@query("lsh_pairs_estimated")
def lsh_pairs_estimated(spark, d):
    _, sets = M.prepared(docs(spark, d), "doc_id", "text")
    return M.verify(M.candidate_pairs(M.lsh_bands(sets)), sets, mode="estimate")


@query("dedup_components", f"{_BASE} select node, component from comp")
def dedup_components(spark, d):
    return components(_edges(spark, d)[1])


@query("dedup_minhash", f"{_BASE}, {_COPIES} select id, coalesce(component, keep) as keep_id from copies left join comp on keep = node")
def dedup_minhash(spark, d):
    return M.minhash_dedup(docs(spark, d), "doc_id", "text")


@query("dedup_first_wins", f"{_BASE}, {_COPIES}, f as (select b, min(a) as a from e group by b) select id, coalesce(a, keep) as keep_id from copies left join f on keep = b")
def dedup_first_wins(spark, d):
    return M.minhash_dedup(docs(spark, d), "doc_id", "text", keep="first")


@query("dedup_greedy")
def dedup_greedy(spark, d):
    return M.minhash_dedup(docs(spark, d), "doc_id", "text", keep="greedy")


@query("dedup_prefer_longest", f"""{_BASE}, {_COPIES}, m as (select c.id, coalesce(component, keep) as g, n from copies c left join comp on keep = node join k on k.id = c.id),
best as (select g, first(id order by n desc, id) as best from m group by g) select id, best as keep_id from m join best using (g)""")
def dedup_prefer_longest(spark, d):
    return M.minhash_dedup(docs(spark, d), "doc_id", "text", prefer=F.length("text"))


@query("dedup_scoped", f"""with recursive k as ({_KEYED}), x as (select ws, source, min(id) as id from k group by all), s as (select id, source, list_distinct(ws) as s from x),
p as (select a.id as a, b.id as b, len(list_intersect(a.s, b.s)) as shared, len(a.s) as na, len(b.s) as nb from s a join s b on a.source = b.source and a.id < b.id and len(a.s) > 0),
e as (select a, b from p where shared::double / (na + nb - shared) >= 0.6),
sym as (select a, b from e union all select b, a from e),
reach as (select a as node, b as other from sym union select r.node, sym.b from reach r join sym on r.other = sym.a),
comp as (select node, least(node, min(other)) as component from reach group by node)
select k.id, coalesce(component, x.id) as keep_id from k join x using (ws, source) left join comp on x.id = node""")
def dedup_scoped(spark, d):
    return M.minhash_dedup(docs(spark, d), "doc_id", "text", scope=["source"])


@query("jaccard_exact_join", f"{_BASE} select a, b, round(similarity, 6) as similarity from e")
def jaccard_exact_join(spark, d):
    return M.exact_similarity_join(word_sets(spark, d)).select("a", "b", F.round("similarity", 6).alias("similarity"))


@query("jaccard_bruteforce", f"""with s as (select item_id as id, list_distinct({words_sql('text')}) as s from benchmark)
select a.id as a, b.id as b, round(len(list_intersect(a.s, b.s))::double / (len(a.s) + len(b.s) - len(list_intersect(a.s, b.s))), 6) as similarity
from s a join s b on a.id < b.id where len(list_intersect(a.s, b.s))::double / (len(a.s) + len(b.s) - len(list_intersect(a.s, b.s))) >= 0.1""")
def jaccard_bruteforce(spark, d):
    from qacurate.registry import read

    sets = read(spark, d, "benchmark").select(F.col("item_id").alias("id"), shingles("text").alias("set"))
    return M.jaccard_bruteforce(sets, 0.1).select("a", "b", F.round("similarity", 6).alias("similarity"))


@query("dedup_ml")
def dedup_ml(spark, d):
    return M.ml_minhash(word_sets(spark, d))


@query("dedup_quality", f"{_BASE} select count(*) as n_found, count(*) as n_true, count(*) as n_both, 1.0::double as recall, 1.0::double as precision from e")
def dedup_quality(spark, d):
    return M.dedup_quality(_edges(spark, d)[1], M.exact_similarity_join(word_sets(spark, d)))


@query("planted_curve")
def planted_curve(spark, d):
    """Found share of planted near copies by similarity, against the closed form of 32 bands of 4 rows."""
    from qacurate.functions.text import md5_fraction, tokens

    # One pass without a join: a document's own signature is made once for all rates and goes along with its copies.
    base = docs(spark, d).where(F.size(shingles("text")) >= 30).select(F.col("doc_id"), tokens("text").alias("w")).withColumn("set", F.array_distinct("w"))
    signed = M.minhash(base).withColumnRenamed("signature", "x").withColumnRenamed("set", "sa")
    rates = F.explode(F.array(*[F.lit(x / 20) for x in range(10)]))
    made = signed.select("doc_id", "w", "sa", "x", rates.alias("rate"))
    copy = F.transform("w", lambda x, i: F.when(md5_fraction(F.col("doc_id"), F.col("rate"), x) < F.col("rate"), F.concat(F.lit("fresh"), i.cast("string"))).otherwise(x))
    pairs = made.select("x", "sa", F.array_distinct(copy).alias("set")).select("x", "set", jaccard("sa", "set").alias("j"))
    copies = M.minhash(pairs, drop=True).withColumnRenamed("signature", "y")
    same = F.exists(F.sequence(F.lit(0), F.lit(31)), lambda i: F.slice("x", i * 4 + 1, 4) == F.slice("y", i * 4 + 1, 4))
    met = copies.select((F.floor(F.col("j") * 20) / 20).alias("bin"), same.cast("int").alias("hit"), (1 - F.pow(1 - F.pow("j", F.lit(4)), F.lit(32))).alias("expected"))
    return met.groupBy("bin").agg(F.count(F.lit(1)).alias("n"), F.round(F.avg("hit"), 4).alias("found"), F.round(F.avg("expected"), 4).alias("expected"))
