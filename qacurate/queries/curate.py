"""Refinement, selection and mixture."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import functions as F

from qacurate.functions.text import md5_fraction, md5_int, n_tokens
from qacurate.operators import extract, mixture, refine, select
from qacurate.queries.common import TURNS_SQL, chunks, docs, labels, spaced_sql, turns, with_sql, words_sql
from qacurate.registry import query, read
from qacurate.staging import stage

# ---- refinement -------------------------------------------------------------------------------


def _pairs(spark, d):
    return extract.extract_pairs(chunks(spark, d), "low")


def _refined(spark, d, strength="strong"):
    c = chunks(spark, d)
    return refine.refine(extract.extract_pairs(c, "low"), c, strength)


def _clean_sql(c: str) -> str:
    return rf"trim(regexp_replace(regexp_replace({c}, '(?i){refine.CITATION}', '', 'g'), '[ \t\r\n]+', ' ', 'g'))"


def weak_sql(table: str = "low") -> str:
    return f"select qid, book_id, chunk_no, {_clean_sql('question')} as question, {_clean_sql('answer')} as answer from {table}"


def strong_sql(table: str = "low") -> str:
    return f"""select qid, w.book_id, w.chunk_no, case when contains(question, head) then question else head || ' ' || question end as question,
  case when contains(answer, tail) then answer else answer || ' ' || tail end as answer
from ({weak_sql(table)}) w join (select book_id, chunk_no, string_split(trim(array_to_string(part, '')), chr(10))[1] as head, string_split(trim(array_to_string(part, '')), chr(10))[-1] as tail from chunks) c using (book_id, chunk_no)"""


_WEAK, _STRONG = weak_sql(), strong_sql()


def _n(c: str) -> str:
    return f"len({words_sql(c)})"


def _sentences(c: str) -> str:
    return rf"len(regexp_extract_all({c}, '[.!?]( |\n|$)'))"


_LACKS = rf"({_sentences('answer')} < 2 or {_n('answer')} < 20 or ({_n('answer')} < 60 and not regexp_matches(lower(answer), '{refine.CONNECTIVES}')))"
_DEFECTS = {
    "external_reference": f"regexp_matches(lower(question), '{refine.REFERENCE}') or regexp_matches(lower(answer), '{refine.REFERENCE}')",
    "contradiction": "regexp_matches(lower(answer), '(?s)contradict|on the one hand.*on the other hand')",
    "missing_information": f"{_n('question')} < 6",
    "invalid": f"{_n('answer')} < 3 or len(list_distinct({words_sql('answer')})) * 4 < {_n('answer')}",
}
_NAMES = "array_to_string(list_filter([" + ", ".join(f"case when {_DEFECTS[k]} then '{k}' end" for k in refine.DEFECTS) + "], lambda x: x is not null), '+')"


@query("refine_pairs", f"{with_sql()} select qid, md5(question) as question, md5(answer) as answer from ({_STRONG})")
def refine_pairs(spark, d):
    return _refined(spark, d).select("qid", F.md5("question").alias("question"), F.md5("answer").alias("answer"))


@query("missing_reasoning", f"{with_sql()} select {_LACKS} as lacks_reasoning, count(*) as n from ({_STRONG}) group by 1")
def missing_reasoning(spark, d):
    return refine.flag_missing_reasoning(_refined(spark, d)).groupBy("lacks_reasoning").agg(F.count(F.lit(1)).alias("n"))


_LAST = r"trim(regexp_extract(answer, '([^.!?]*)[.!?]?\s*$', 1))"


def supplemented_sql(table: str) -> str:
    return f"select qid, question, case when {_LACKS} then 'Step 1: the question states: ' || question || ' Step 2: ' || answer || ' Therefore the final answer is: ' || {_LAST} || '.' else answer end as answer from ({table})"


_SUPPLEMENTED = supplemented_sql(_STRONG)


@query("supplement_cot", f"{with_sql()} select qid, length(answer)::bigint as n_chars from ({_SUPPLEMENTED})")
def supplement_cot(spark, d):
    out = refine.supplement(refine.flag_missing_reasoning(_refined(spark, d)))
    return out.select("qid", F.length("answer").cast("long").alias("n_chars"))


@query("defect_filter", f"{with_sql()} select qid from ({_STRONG}) where {_NAMES} = ''")
def defect_filter(spark, d):
    return refine.drop_defective(_refined(spark, d))[0].select("qid")


@query("defect_reasons", f"{with_sql()} select {_NAMES} as defects, count(*) as n from ({_STRONG}) where {_NAMES} <> '' group by 1")
def defect_reasons(spark, d):
    return refine.drop_defective(_refined(spark, d))[1].groupBy(F.array_join("defects", "+").alias("defects")).agg(F.count(F.lit(1)).alias("n"))


def _compare(name: str, table: str) -> str:
    return f"select '{name}' as refiner, count(*) as n, count_if({_LACKS}) as n_lacking, count_if({_NAMES} <> '') as n_defective, sum({_n('answer')})::bigint as answer_words from ({table})"


@query("refiner_compare", f"{with_sql()} {_compare('weak', _WEAK)} union all {_compare('strong', _STRONG)}")
def refiner_compare(spark, d):
    def row(strength):
        x = refine.flag_missing_reasoning(_refined(spark, d, strength)).withColumn("bad", F.size(refine.defects()) > 0)
        return x.agg(F.count(F.lit(1)).alias("n"), F.count_if("lacks_reasoning").alias("n_lacking"), F.count_if("bad").alias("n_defective"), F.sum(n_tokens("answer")).cast("long").alias("answer_words")).select(F.lit(strength).alias("refiner"), "*")

    return row("weak").union(row("strong"))


# ---- selection --------------------------------------------------------------------------------

#: Pairs of turns in four slices that stand for the sources, by conversation. Answers of B end in an option, those of C
#: are long and say things again. Planted: copies of questions of every fifth conversation, benchmark items as questions
#: of A and B, and answers of B that are longer than the mixture allows.
_SLICE = "case conv_id % 4 when 0 then 'textbook' when 1 then 'A' when 2 then 'B' else 'C' end"
_OPTION = "chr(10) || 'The correct option is ' || substr('ABCD', (turn % 4 + 1)::int, 1) || ' for the reasons that the text above has given in its own words'"
_BASE_QA = f"""select qid, question, dataset, case dataset when 'B' then answer || {_OPTION} when 'C' then 'We repeat every step. ' || answer || ' ' || answer || ' ' || answer else answer end as answer, conv_id, turn
  from (select *, {_SLICE} as dataset from ({TURNS_SQL}))"""
_ITEM_ANSWER = "The answer to this question is known because the text above says so in its own words."
_LONG_QUESTION = "'Describe ' || md5('l' || qid) || ' ' || md5('m' || qid) || ' ' || md5('n' || qid) || ' ' || md5('o' || qid) || ' in full'"
QA = f"""base_qa as ({_BASE_QA}), qa as (select qid, question, answer, dataset from base_qa
  union all select qid || ':copy', question || ' please', answer, dataset from base_qa where conv_id % 5 = 0
  union all select 'leak:' || item_id, 'Please answer this. ' || text, '{_ITEM_ANSWER}', case item_id % 2 when 0 then 'A' else 'B' end from benchmark
  union all select qid || ':long', {_LONG_QUESTION}, repeat('step ', 4200) || chr(10) || 'The correct option is the one that case ' || md5('l' || qid) || ' has by its rules', 'B' from base_qa where conv_id % 11 = 0)"""


def qa(spark, d):
    k, option = F.col("conv_id") % 4, F.substr(F.lit("ABCD"), (F.col("turn") % 4 + 1).cast("int"), F.lit(1))
    named = turns(spark, d).withColumn("dataset", F.when(k == 0, "textbook").when(k == 1, "A").when(k == 2, "B").otherwise("C"))
    b = F.concat("answer", F.lit("\nThe correct option is "), option, F.lit(" for the reasons that the text above has given in its own words"))
    c = F.concat(F.lit("We repeat every step. "), "answer", F.lit(" "), "answer", F.lit(" "), "answer")
    base = named.withColumn("answer", F.when(F.col("dataset") == "B", b).when(F.col("dataset") == "C", c).otherwise(F.col("answer")))
    tag = lambda x: F.md5(F.concat(F.lit(x), "qid"))
    copies = base.where("conv_id % 5 = 0").select(F.concat("qid", F.lit(":copy")).alias("qid"), F.concat("question", F.lit(" please")).alias("question"), "answer", "dataset")
    items = read(spark, d, "benchmark").select(F.concat(F.lit("leak:"), F.col("item_id").cast("string")).alias("qid"), F.concat(F.lit("Please answer this. "), "text").alias("question"), F.lit(_ITEM_ANSWER).alias("answer"), F.when(F.col("item_id") % 2 == 0, "A").otherwise("B").alias("dataset"))
    long_q = F.concat_ws(" ", F.lit("Describe"), tag("l"), tag("m"), tag("n"), tag("o"), F.lit("in full"))
    long_a = F.concat(F.repeat(F.lit("step "), F.lit(4200)), F.lit("\nThe correct option is the one that case "), tag("l"), F.lit(" has by its rules"))
    long_ = base.where("conv_id % 11 = 0").select(F.concat("qid", F.lit(":long")).alias("qid"), long_q.alias("question"), long_a.alias("answer"), F.lit("B").alias("dataset"))
    return base.select("qid", "question", "answer", "dataset").unionByName(copies).unionByName(items).unionByName(long_)


def _by_length(spark, d):
    return select.lengths(docs(spark, d).select("doc_id", "text"), "text")


_LONGEST = f"select doc_id, {_n('text')} as length from documents order by length desc, doc_id limit 100"


@query("select_longest", _LONGEST)
def select_longest(spark, d):
    return select.select_longest(_by_length(spark, d), 100, id_="doc_id").select("doc_id", "length")


@query("select_longest_hist", _LONGEST)
def select_longest_hist(spark, d):
    return select.select_longest_hist(_by_length(spark, d).select("doc_id", "length"), 100, id_="doc_id").select("doc_id", "length")


_REF = r"""ref as (select *, case dataset when 'textbook' then trim(regexp_extract(answer, '([^.!?]*[.!?]?)\s*$', 1)) when 'B' then trim(string_split(answer, chr(10))[-1]) else answer end as reference from qa)"""
_FRACTION = "(('0x' || substr(md5({}), 1, 8))::bigint / 4294967296.0)"
_SAID = f"{_FRACTION.format("qid || ':' || k || ':' || w")} >= hard"
_RESP = f"""resp as (select qid, k, reference, list_filter({words_sql('reference')}, lambda w: {_SAID}) as r
  from (select *, 1.2::double * {_FRACTION.format("'h:' || qid")} - 0.1::double as hard from ref), (select unnest(range(1, 17)) as k))"""
_A, _B = "list_distinct(r)", f"list_distinct({words_sql('reference')})"
_SCORES = f"scores as (select qid, k, floor(coalesce(2.0 * len(list_intersect({_A}, {_B})) / nullif(len({_A}) + len({_B}), 0), 0) * 10 + 0.5)::int as score from resp)"
_MEANS = "means as (select qid, count(*) as n, sum(score)::bigint as total, sum(score)::double / count(*) as mean from scores group by qid)"
CHAIN = f"with {QA}, {_REF}, {_RESP}, {_SCORES}, {_MEANS}"


def _scores(spark, d):
    return select.score_responses(select.sample_responses(select.reference_answers(qa(spark, d))))


def means(spark, d):
    return select.mean_scores(select.reference_answers(qa(spark, d))).select("qid", "n", "total", "mean")


@query("reference_policy", f"with {QA}, {_REF} select qid, dataset, md5(reference) as reference from ref")
def reference_policy(spark, d):
    return select.reference_answers(qa(spark, d)).select("qid", "dataset", F.md5("reference").alias("reference"))


@query("sampled_responses", f"with {QA}, {_REF}, {_RESP} select qid, k::int as k, md5(array_to_string(r, ' ')) as response from resp")
def sampled_responses(spark, d):
    return select.sample_responses(select.reference_answers(qa(spark, d))).select("qid", "k", F.md5("response").alias("response"))


@query("response_scores", f"{CHAIN} select qid, k::int as k, score from scores")
def response_scores(spark, d):
    return _scores(spark, d).select("qid", "k", "score")


@query("difficulty_scores", f"{CHAIN} select qid, n, total, round(mean, 6) as mean from means")
def difficulty_scores(spark, d):
    """From the responses themselves, one row per draw."""
    return select.difficulty(_scores(spark, d)).select("qid", "n", "total", F.round("mean", 6).alias("mean"))


@query("difficulty_in_one_row", f"{CHAIN} select qid, n, total, round(mean, 6) as mean from means")
def difficulty_in_one_row(spark, d):
    return means(spark, d).select("qid", "n", "total", F.round("mean", 6).alias("mean"))


@query("select_difficulty", f"{CHAIN} select qid from means where total between 1 * n and 9 * n")
def select_difficulty(spark, d):
    return select.select_by_difficulty(means(spark, d)).select("qid")


@query("hard_subset", f"{CHAIN} select qid from means where total < 6 * n")
def hard_subset(spark, d):
    return select.hard_subset(means(spark, d)).select("qid")


@query("score_bounds", "select total::bigint as total, total between 16 and 144 as kept, total < 96 as hard from (values (15), (16), (95), (96), (144), (145)) t(total)")
def score_bounds(spark, d):
    """Means at the bounds: 16 scores with known sums."""
    sums = spark.createDataFrame([(x,) for x in (15, 16, 95, 96, 144, 145)], "total long").withColumn("n", F.lit(16))
    kept, hard = select.select_by_difficulty(sums).select("total", F.lit(True).alias("kept")), select.hard_subset(sums).select("total", F.lit(True).alias("hard"))
    out = sums.select("total").join(kept, "total", "left").join(hard, "total", "left")
    return out.select("total", F.coalesce("kept", F.lit(False)).alias("kept"), F.coalesce("hard", F.lit(False)).alias("hard"))


@query("distil_vs_refine", f"{CHAIN} select mean < 6 as distilled, count(*) as n, sum(case when mean < 6 then 2 * length(answer) + 41 else length(answer) end)::bigint as chars from qa join means using (qid) group by 1")
def distil_vs_refine(spark, d):
    scored = qa(spark, d).join(means(spark, d).select("qid", F.col("mean").alias("score")), "qid")
    return refine.difficulty_aware_distil(scored).groupBy("distilled").agg(F.count(F.lit(1)).alias("n"), F.sum(F.length("answer")).cast("long").alias("chars"))


_KEY = "('0x' || substr(md5('s:' || {}), 1, 12))::bigint"


@query("select_random", f"select doc_id from documents order by {_KEY.format('doc_id')}, doc_id limit 100")
def select_random(spark, d):
    return select.select_random(docs(spark, d), 100, "doc_id").select("doc_id")


@query("select_stratified", f"select doc_id, lang from (select *, row_number() over (partition by lang order by {_KEY.format('doc_id')}, doc_id) as r, count(*) over (partition by lang) as n from documents) where r <= ceil(n * 0.2)")
def select_stratified(spark, d):
    return select.select_stratified(docs(spark, d), "lang", 0.2, "doc_id").select("doc_id", "lang")


# The matched size n is the difficulty selection's; length and random then keep n each.
_SIZES = f"""{CHAIN}, m as (select qid, question, answer, dataset, total, n, {_n('answer')} as length, {_KEY.format('qid')} as key from qa join means using (qid) where dataset <> 'C'),
dif as (select qid, dataset from m where total between n and 9 * n), size as (select dataset, count(*) as k from dif group by dataset),
len as (select qid, dataset from (select *, row_number() over (partition by dataset order by length desc, qid) as r from m) join size using (dataset) where r <= k),
rnd as (select qid, dataset from (select *, row_number() over (partition by dataset order by key, qid) as r from m) join size using (dataset) where r <= k),
picked as (select 'all' as strategy, qid, dataset from m union all select 'difficulty', qid, dataset from dif union all select 'length', qid, dataset from len union all select 'random', qid, dataset from rnd)"""


def picked(spark, d):
    """(strategy, qid, dataset): the subsets of each source by each strategy, at the size difficulty gives."""
    scored = stage(select.lengths(qa(spark, d).where("dataset <> 'C'").join(means(spark, d), "qid")).drop("question", "answer"), "scored")
    parts = []
    for source in ("textbook", "A", "B"):
        own = scored.where(F.col("dataset") == source)
        dif = select.select_by_difficulty(own)
        n = dif.count()
        chosen = {"all": own, "difficulty": dif, "length": select.select_longest(own, n), "random": select.select_random(own, n)}
        parts += [df.select(F.lit(s).alias("strategy"), "qid", "dataset") for s, df in chosen.items()]
    return reduce(lambda x, y: x.unionByName(y), parts)


@query("strategy_sizes", f"{_SIZES} select dataset, strategy, count(*) as n from picked group by all")
def strategy_sizes(spark, d):
    return picked(spark, d).groupBy("dataset", "strategy").agg(F.count(F.lit(1)).alias("n"))


@query("strategy_overlap", f"{_SIZES} select a.dataset, a.strategy as s1, b.strategy as s2, count(*) as n from picked a join picked b on a.qid = b.qid and a.strategy < b.strategy group by all")
def strategy_overlap(spark, d):
    p = picked(spark, d)
    a, b = p.select("dataset", "qid", F.col("strategy").alias("s1")), p.select("qid", F.col("strategy").alias("s2"))
    return a.join(b, "qid").where("s1 < s2").groupBy("dataset", "s1", "s2").agg(F.count(F.lit(1)).alias("n"))


_DOC_CHAIN = f"""with l as (select d.doc_id, d.text, quality from documents d join labels l using (doc_id)),
ref as (select doc_id::varchar as qid, trim(regexp_extract(text, '([^.!?]*[.!?]?)\\s*$', 1)) as reference from l), {_RESP}, {_SCORES}, {_MEANS},
m as (select l.*, total, n, {_n('text')} as length, {_KEY.format('doc_id')} as key from l join means on qid = doc_id::varchar),
dif as (select * from m where total between n and 9 * n), size as (select count(*) as k from dif),
r as (select *, row_number() over (order by length desc, doc_id) as rl, row_number() over (order by key, doc_id) as rr from m)"""


def labelled(spark, d):
    """(doc_id, text, quality, length, total, n, mean): labelled documents with the difficulty of their last sentence."""
    rows = docs(spark, d).select("doc_id", "text").join(labels(spark, d).select("doc_id", "quality"), "doc_id")
    asked = select.reference_answers(rows.withColumns({"qid": F.col("doc_id").cast("string"), "answer": F.col("text"), "dataset": F.lit("textbook")}))
    return select.lengths(select.mean_scores(asked), "text").select("doc_id", "text", "quality", "length", "total", "n", "mean")


@query("strategy_quality", f"""{_DOC_CHAIN} select 'all' as strategy, count(*) as n, sum(quality)::bigint as good from r
union all select 'difficulty', count(*), sum(quality)::bigint from dif
union all select 'length', count(*), sum(quality)::bigint from r, size where rl <= k
union all select 'random', count(*), sum(quality)::bigint from r, size where rr <= k""")
def strategy_quality(spark, d):
    from qacurate.operators.proxy import subsets

    own = stage(labelled(spark, d).drop("text"), "labelled")
    parts = [df.agg(F.lit(s).alias("strategy"), F.count(F.lit(1)).alias("n"), F.sum("quality").cast("long").alias("good")) for s, df in subsets(own).items()]
    return reduce(lambda x, y: x.unionByName(y), parts)


@query("strategy_choice")
def strategy_choice(spark, d):
    """Proxy accuracy of each strategy's subset; see qacurate.operators.proxy."""
    from qacurate.operators.proxy import compare_strategies

    return compare_strategies(labelled(spark, d))


# ---- mixture ----------------------------------------------------------------------------------

_ANNOTATED = "select qid, dataset, question, case when dataset in ('A', 'B') then 'Step 1: read the question. Step 2: ' || answer || ' Therefore the final answer is given above.' else answer end as answer from qa"


@query("annotation_policy", f"with {QA} select dataset, count(*) as n, sum(length(answer))::bigint as chars from ({_ANNOTATED}) group by dataset")
def annotation_policy(spark, d):
    return mixture.annotate(qa(spark, d)).groupBy("dataset").agg(F.count(F.lit(1)).alias("n"), F.sum(F.length("answer")).cast("long").alias("chars"))


@query("drop_overlong", f"select doc_id from documents where len({spaced_sql('text')}) <= 512")
def drop_overlong(spark, d):
    return mixture.drop_overlong(docs(spark, d), 512, "text").select("doc_id")


@query("overlong_bounds", f"select doc_id, n::bigint as n, n <= 4096 as kept from (select doc_id, greatest(len({spaced_sql('text')}), 4096 + doc_id % 2) as n from documents)")
def overlong_bounds(spark, d):
    """Texts filled up to 4,096 tokens or one more, by id: only the first stay."""
    lack = F.greatest(4096 + F.col("doc_id") % 2 - F.coalesce(n_tokens("text", "space"), F.lit(0)), F.lit(0)).cast("int")
    made = docs(spark, d).select("doc_id", F.concat(F.coalesce("text", F.lit("")), F.repeat(F.lit(" w"), lack)).alias("answer"))
    made = made.withColumn("n", n_tokens("answer", "space").cast("long"))
    return made.select("doc_id", "n").join(mixture.drop_overlong(made).select("doc_id", F.lit(True).alias("kept")), "doc_id", "left").select("doc_id", "n", F.coalesce("kept", F.lit(False)).alias("kept"))


def mixed(spark, d):
    """The mixture: textbook whole, A at random, B by difficulty, annotated, over-long answers dropped."""
    rows, chosen = qa(spark, d), stage(picked(spark, d), "picked")
    parts = {s.name: rows.join(chosen.where((F.col("strategy") == s.strategy) & (F.col("dataset") == s.name)).select("qid"), "qid", "left_semi") for s in mixture.SPECS if s.include}
    return mixture.drop_overlong(mixture.annotate(mixture.build_mixture(parts)))


_PICK = "(select * from picked where (dataset = 'textbook' and strategy = 'all') or (dataset = 'A' and strategy = 'random') or (dataset = 'B' and strategy = 'difficulty'))"


@query("mixture", f"{_SIZES} select qid, dataset, length(answer)::bigint as n_chars from ({_ANNOTATED}) join (select qid from {_PICK}) using (qid) where len({spaced_sql('answer')}) <= 4096")
def mixture_(spark, d):
    return mixed(spark, d).select("qid", "dataset", F.length("answer").cast("long").alias("n_chars"))


_STAGES = f"""{_SIZES}, st as (select 0 as stage_no, 'raw' as stage, dataset from qa where dataset <> 'C' union all select 1, 'scored', dataset from m union all select 2, 'selected', dataset from {_PICK}),
counts as (select stage_no, stage, dataset, count(*) as n from st group by all union all select stage_no, stage, 'total', count(*) from st group by all)"""


def _stage_counts(spark, d):
    rows, chosen = qa(spark, d).where("dataset <> 'C'"), stage(picked(spark, d), "picked")
    scored = rows.join(means(spark, d).select("qid"), "qid", "left_semi")
    kept = chosen.where("(dataset = 'textbook' and strategy = 'all') or (dataset = 'A' and strategy = 'random') or (dataset = 'B' and strategy = 'difficulty')")
    return mixture.stage_counts([("raw", rows), ("scored", scored), ("selected", kept)], "dataset")


@query("stage_counts", f"{_STAGES} select * from counts")
def stage_counts(spark, d):
    return _stage_counts(spark, d)


@query("stage_counts_pivot", f"{_STAGES} select dataset, max(n) filter (stage = 'raw') as raw, max(n) filter (stage = 'scored') as scored, max(n) filter (stage = 'selected') as selected from counts group by dataset")
def stage_counts_pivot(spark, d):
    return mixture.pivot_stages(_stage_counts(spark, d), "dataset", ["raw", "scored", "selected"])


@query("export_chat", f"select qid, json_array(json_object('role', 'user', 'content', question), json_object('role', 'assistant', 'content', answer))::varchar as messages from ({TURNS_SQL})")
def export_chat(spark, d):
    return mixture.to_chat(turns(spark, d))


@query("lineitem_difficulty", """with s as (select l_partkey, (l_quantity - 1) / 49 * 10 as score, row_number() over (partition by l_partkey order by l_orderkey, l_linenumber) as k from lineitem),
m as (select l_partkey, avg(score) as mean from s where k <= 16 group by l_partkey)
select least(floor(mean), 9)::int as band, count(*) as n, count_if(mean between 1 and 9) as n_kept, count_if(mean < 6) as n_hard from m group by 1""")
def lineitem_difficulty(spark, d):
    """Sixteen scores per question at scale: lines of a part stand for its sampled responses."""
    from pyspark.sql import Window

    k = F.row_number().over(Window.partitionBy("l_partkey").orderBy("l_orderkey", "l_linenumber"))
    scores = read(spark, d, "lineitem").select("l_partkey", ((F.col("l_quantity") - 1) / 49 * 10).alias("score"), k.alias("k")).where("k <= 16")
    m = scores.groupBy("l_partkey").agg(F.avg("score").alias("mean"))
    return m.groupBy(F.least(F.floor("mean"), F.lit(9)).cast("int").alias("band")).agg(F.count(F.lit(1)).alias("n"), F.count_if(F.col("mean").between(1, 9)).alias("n_kept"), F.count_if(F.col("mean") < 6).alias("n_hard"))


@query("sample_bernoulli_md5", "select doc_id from documents where ('0x' || substr(md5('b:' || doc_id), 1, 8))::bigint / 4294967296.0 < 0.1")
def sample_bernoulli_md5(spark, d):
    return docs(spark, d).where(md5_fraction("b", F.col("doc_id").cast("string")) < 0.1).select("doc_id")


@query("split_md5", "select case when ('0x' || substr(md5('x:' || doc_id), 1, 8))::bigint % 10 < 8 then 'train' else 'held_out' end as part, count(*) as n from documents group by 1")
def split_md5(spark, d):
    k = md5_int(F.concat(F.lit("x:"), F.col("doc_id").cast("string")))
    return docs(spark, d).groupBy(F.when(k % 10 < 8, "train").otherwise("held_out").alias("part")).agg(F.count(F.lit(1)).alias("n"))
