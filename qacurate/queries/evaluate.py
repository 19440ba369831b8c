"""Evaluation suite, extraction, grading and measures."""

from __future__ import annotations

from pyspark.sql import functions as F

from qacurate.functions import published as P
from qacurate.functions.text import n_tokens
from qacurate.operators import answers as A
from qacurate.operators import evalsuite as E
from qacurate.operators import measures as M
from qacurate.operators.ngram import ngram_decontaminate
from qacurate.queries.common import docs, labels, words_sql
from qacurate.queries.curate import CHAIN, QA, means, qa
from qacurate.queries.decontam import _gram_sql
from qacurate.registry import query, read

# ---- suite ------------------------------------------------------------------------------------

_REG = P.values_sql(E.REGISTRY, "slot, benchmark, category, subject, kind, needs_unit, in_average")


@query("eval_registry", f"select r.*, case when needs_unit then 'EM (unit)' else 'EM' end as metric, coalesce(n, 0) as n_items from {_REG} r left join (select p_partkey % 15 as slot, count(*) as n from part group by 1) using (slot)")
def eval_registry(spark, d):
    """The registry, with the items that the parts give each benchmark."""
    counts = items(spark, d).groupBy("benchmark").agg(F.count(F.lit(1)).alias("n"))
    return E.registry(spark).join(counts, "benchmark", "left").withColumn("n_items", F.coalesce("n", F.lit(0))).drop("n")


def items(spark, d):
    return E.items(read(spark, d, "part"), E.registry(spark))


#: The rendered items and planted responses again, for the oracles.
_ITEMS = f"""items as (select benchmark, category, in_average, needs_unit, p_partkey as item_id,
  case when kind = 'mixed' then case when p_partkey % 2 = 0 then 'choice' else 'computational' end else kind end as qtype, p_size, p_brand,
  substr('ABCD', (p_partkey % 4 + 1)::int, 1) as label from part join {_REG} r on r.slot = p_partkey % 15),
gold as (select *, case qtype when 'choice' then label when 'truefalse' then case when item_id % 2 = 0 then 'true' else 'false' end else p_size::varchar end as gold from items)"""
_GRID = f"""{_ITEMS}, grid as (select g.*, k, 'system_' || k as model, (item_id + 7 * k) % 10 < 3 + k as is_right, ((item_id + k) % 8)::int as template from gold g, (select unnest(range(0, {E.MODELS})) as k)),
planted as (select *, is_right and template <> 7 and not (template = 6 and needs_unit) as ok from grid)"""


@query("render_prompts", "select item_id, 'user: Reason step by step, then give the final answer.' || chr(10) || 'Q: What is 1 + 1?' || chr(10) || 'A: The final answer is 2.' || chr(10) || chr(10) || text as chat, 'Q: ' || text || chr(10) || 'A:' as base from benchmark")
def render_prompts(spark, d):
    b = read(spark, d, "benchmark")
    chat, base = E.EvalTask("x", "chat", shots=1), E.EvalTask("x", "base", reasoning=False)
    return b.select("item_id", E.render_prompt(F.col("text"), chat).alias("chat"), E.render_prompt(F.col("text"), base).alias("base"))


@query("eval_grid", f"with {_GRID} select model, benchmark, count(*) as n from grid group by all")
def eval_grid(spark, d):
    return E.responses(items(spark, d)).groupBy("model", "benchmark").agg(F.count(F.lit(1)).alias("n"))


@query("instance_output", f"with {_GRID} select model, benchmark, item_id, ok as correct from planted")
def instance_output(spark, d):
    return E.evaluate(items(spark, d)).select("model", "benchmark", "item_id", "correct")


@query("benchmark_accuracy", f"with {_GRID} select model, benchmark, count(*) as n, count_if(ok) as n_correct, ((2 * count_if(ok) * 10000 + count(*)) // (2 * count(*)))::bigint as cents from planted group by all")
def benchmark_accuracy(spark, d):
    return M.benchmark_accuracy(E.evaluate(items(spark, d)))


@query("graded_averages", f"""with {_GRID}, b as (select model, benchmark, category, ((2 * count_if(ok) * 10000 + count(*)) // (2 * count(*)))::bigint as cents from planted where in_average group by all)
select model as system, coalesce(category, 'Overall') as category, count(*) as n, ((2 * sum(cents) + count(*)) // (2 * count(*)))::bigint as cents from b group by grouping sets ((model, category), (model))""")
def graded_averages(spark, d):
    rows = E.evaluate(items(spark, d)).where("in_average")
    acc = M.benchmark_accuracy(rows).join(E.registry(spark).select("benchmark", "category"), "benchmark")
    return M.category_averages(acc.withColumnRenamed("model", "system"))


@query("extraction_by_template", f"with {_GRID} select template, count(*) as n, count_if(ok) as n_correct, count_if(template = 7) as n_none from planted group by template")
def extraction_by_template(spark, d):
    return E.evaluate(items(spark, d)).groupBy("template").agg(F.count(F.lit(1)).alias("n"), F.count_if("correct").alias("n_correct"), F.count_if(F.col("rule") == "r9").alias("n_none"))


@query("extraction_report")
def extraction_report(spark, d):
    return A.extraction_report(E.evaluate(items(spark, d)))


@query("boxed_only", f"with {_GRID} select template in (0, 1) as boxed, count(*) as n from grid group by 1")
def boxed_only(spark, d):
    r = E.responses(items(spark, d))
    return r.groupBy(A.extract_boxed_only(F.col("response")).isNotNull().alias("boxed")).agg(F.count(F.lit(1)).alias("n"))


@query("boxed_vs_cascade", f"with {_GRID} select model, count_if(ok) as cascade, count_if(ok and template in (0, 1)) as boxed from planted group by model")
def boxed_vs_cascade(spark, d):
    full = E.evaluate(items(spark, d)).groupBy("model").agg(F.count_if("correct").alias("cascade"))
    only = A.grade(E.responses(items(spark, d)).withColumn("answer", A.extract_boxed_only(F.col("response")))).groupBy("model").agg(F.count_if("correct").alias("boxed"))
    return full.join(only, "model")


def _null(x):
    return "null" if x is None else "'" + x.replace("'", "''") + "'"


#: What follows the indicator phrase in each form of a response, and the same unwrapped.
_SAID = f"""{_GRID}, valued as (select *, case when is_right then gold when qtype = 'choice' then case when gold = 'A' then 'B' else 'A' end
  when qtype = 'truefalse' then case when gold = 'true' then 'false' else 'true' end else (gold::int + 1000)::varchar end as value from grid),
said as (select model, item_id, template, value || case when template = 6 and needs_unit then ' kg' when needs_unit then ' m' else '' end as inner_ from valued)"""


@query("answer_indicator", f"with {_SAID} select model, item_id, case template when 0 then '\\boxed{{' || inner_ || '}}.' when 2 then '**' || inner_ || '**' when 3 then inner_ || '.' when 4 then inner_ when 6 then inner_ || '.' end as said from said")
def answer_indicator(spark, d):
    return E.responses(items(spark, d)).select("model", "item_id", A.find_indicator(F.col("response")).alias("said"))


@query("answer_unwrap", f"with {_SAID} select model, item_id, case when template in (0, 2, 3, 4, 6) then inner_ end as value from said")
def answer_unwrap(spark, d):
    return E.responses(items(spark, d)).select("model", "item_id", A.unwrap(A.find_indicator(F.col("response"))).alias("value"))


@query("answer_extract", f"with {_GRID} select model, benchmark, item_id, template <> 7 as extracted from grid where qtype = 'computational'")
def answer_extract(spark, d):
    rows = A.extract_answer(E.responses(items(spark, d))).where("qtype = 'computational'")
    return rows.select("model", "benchmark", "item_id", F.col("answer").isNotNull().alias("extracted"))


@query("option_fallback", f"with {_GRID} select model, item_id, case when is_right then gold when gold = 'A' then 'B' else 'A' end as answer from grid where qtype = 'choice' and template = 5")
def option_fallback(spark, d):
    rows = E.responses(items(spark, d)).where("qtype = 'choice' and template = 5")
    return rows.select("model", "item_id", A.match_option(F.col("response"), F.col("options")).alias("answer"))


#: Value, number, unit.
VALUES = (("12 meters", 12.0, "m"), ("1,250.5 kg", 1250.5, "kg"), ("7/2", 3.5, None), ("3.2e3 Seconds", 3200.0, "s"), ("45%", 45.0, "%"), ("-8", -8.0, None), ("none", None, None))


@query("unit_split", "select * from (values " + ", ".join(f"({_null(a)}, {'null' if b is None else b}::double, {_null(c)})" for a, b, c in VALUES) + ") t(value, number, unit)")
def unit_split(spark, d):
    v = spark.createDataFrame([(a,) for a, _, _ in VALUES], "value string")
    s = A.split_unit(F.col("value"))
    return v.select("value", s["number"].alias("number"), F.when(s["number"].isNotNull(), s["unit"]).alias("unit"))


def _grade_query(name: str, where: str) -> None:
    @query(name, f"with {_GRID} select model, count(*) as n, count_if(ok) as n_correct from planted where {where} group by model")
    def run(spark, d):
        rows = E.evaluate(items(spark, d)).where(where)
        return rows.groupBy("model").agg(F.count(F.lit(1)).alias("n"), F.count_if("correct").alias("n_correct"))


_grade_query("grade_em", "not needs_unit and qtype = 'choice'")
_grade_query("grade_em_unit", "needs_unit")
_grade_query("grade_mixed", "benchmark in ('CS-Bench', 'ChemBench')")


@query("lineitem_predictions", """select 'm' || (l_suppkey % 6) as model, 'b' || (l_partkey % 14) as benchmark, count(*) as n, count_if(l_linenumber % 3 <> 0) as n_correct,
  ((2 * count_if(l_linenumber % 3 <> 0) * 10000 + count(*)) // (2 * count(*)))::bigint as cents from lineitem group by all""")
def lineitem_predictions(spark, d):
    """Throughput grid: a prediction per line, extracted, graded and averaged."""
    li = read(spark, d, "lineitem")
    q = F.col("l_quantity").cast("int")
    value = F.when(F.col("l_linenumber") % 3 != 0, q).otherwise(q + 100).cast("string")
    text = F.when(F.col("l_orderkey") % 2 == 0, F.concat(F.lit("So the final answer is \\boxed{"), value, F.lit("}."))).otherwise(F.concat(F.lit("Thus.\nThe answer is "), value, F.lit(".")))
    rows = li.select(F.concat(F.lit("m"), F.col("l_suppkey") % 6).alias("model"), F.concat(F.lit("b"), F.col("l_partkey") % 14).alias("benchmark"), text.alias("response"), q.cast("string").alias("gold"), F.lit("computational").alias("qtype"), F.lit(None).cast("map<string,string>").alias("options"), F.lit(False).alias("needs_unit"), F.lit(None).cast("string").alias("gold_unit"))
    return M.benchmark_accuracy(A.grade(A.extract_answer(rows)))


# ---- measures on published scores -------------------------------------------------------------

_SCORES = P.values_sql(P.main_scores(), "system, benchmark, category, cents")
_AVG = f"(select system, coalesce(category, 'Overall') as category, count(*) as n, ((2 * sum(cents) + count(*)) // (2 * count(*)))::bigint as cents from {_SCORES} group by grouping sets ((system, category), (system)))"
_RANKED = f"(select benchmark, system, cents, dense_rank() over (partition by benchmark order by cents desc)::int as rank from {_SCORES})"


#: Scores of the planted responses: the same measures on graded rows.
_CENTS = "((2 * {0} * 10000 + count(*)) // (2 * count(*)))::bigint"
_GRADED = f"{_GRID}, scores as (select model as system, benchmark, category, {_CENTS.format('count_if(ok)')} as cents from planted group by all)"
_GRADED_AVG = f"{_GRADED}, avgs as (select system, coalesce(category, 'Overall') as category, count(*) as n, ((2 * sum(cents) + count(*)) // (2 * count(*)))::bigint as cents from scores group by grouping sets ((system, category), (system)))"


def graded_scores(spark, d):
    accuracy = M.benchmark_accuracy(E.evaluate(items(spark, d)))
    return accuracy.join(E.registry(spark).select("benchmark", "category"), "benchmark").withColumnRenamed("model", "system")


@query("category_averages", f"with {_GRADED_AVG} select * from avgs")
def category_averages(spark, d):
    return M.category_averages(graded_scores(spark, d))


@query("best_second", f"with {_GRADED} select benchmark, system, cents, dense_rank() over (partition by benchmark order by cents desc)::int as rank from scores qualify rank <= 2")
def best_second(spark, d):
    return M.best_second(graded_scores(spark, d))


@query("win_counts", f"select system, count_if(rank = 1) as wins, count_if(rank = 2) as seconds from {_RANKED} where rank <= 2 group by system")
def win_counts(spark, d):
    return M.win_counts(P.scores(spark))


@query("gain_vs_baseline", f"with {_GRADED_AVG} select a.system, category, a.cents - b.cents as gain from avgs a join avgs b using (category) where b.system = 'system_0' and a.system <> 'system_0'")
def gain_vs_baseline(spark, d):
    return M.gain_vs_baseline(graded_scores(spark, d), "system_0")


@query("unpivot_scores", f"select benchmark, system, cents from {_SCORES}")
def unpivot_scores(spark, d):
    wide = P.scores(spark).groupBy("benchmark").pivot("system", list(P.SYSTEMS)).agg(F.first("cents"))
    return wide.unpivot("benchmark", list(P.SYSTEMS), "system", "cents")


_FAMILIES = P.values_sql([(f, s, round(a * 100), round(b * 100)) for f, s, a, b in P.FAMILIES], "family, size, instruct, trained")


@query("scaling_gap", f"select family, size::double as size, (trained - instruct)::bigint as gap, ((trained - instruct) - lag(trained - instruct) over (partition by family order by size))::bigint as change from {_FAMILIES}")
def scaling_gap(spark, d):
    rows = [(f, s, round(a * 100), round(b * 100)) for f, s, a, b in P.FAMILIES]
    return M.scaling_gap(spark.createDataFrame(rows, "family string, size double, instruct long, trained long"))


@query("ablation_delta", f"""with {_GRID}, studies as (select model as study, 'full' as variant, {_CENTS.format('count_if(ok)')} as cents from planted group by model
union all select model, 'boxed', {_CENTS.format('count_if(ok and template in (0, 1))')} from planted group by model)
select a.study, a.variant, a.cents - b.cents as delta from studies a join studies b using (study) where b.variant = 'full' and a.variant <> 'full'""")
def ablation_delta(spark, d):
    """Each system's accuracy by the whole cascade and without all rules but the boxed one."""
    full = E.evaluate(items(spark, d))
    boxed = A.grade(E.responses(items(spark, d)).withColumn("answer", A.extract_boxed_only(F.col("response"))))
    scored = [x.groupBy(F.col("model").alias("study")).agg(M.half_up(F.count_if("correct") * 10000, F.count(F.lit(1))).alias("cents")).withColumn("variant", F.lit(v)) for v, x in (("full", full), ("boxed", boxed))]
    return M.ablation_delta(scored[0].unionByName(scored[1]))


_LEAKED = _gram_sql(13, "select source, (after - before)::bigint as delta, after < before as falls from changed").replace("select source", """, leaked as (select distinct id from q join b using (g)),
marked as (select source, quality, leaked.id is null as stays from documents join labels using (doc_id) left join leaked on doc_id = leaked.id),
changed as (select source, (2 * count_if(quality = 1) * 10000 + count(*)) // (2 * count(*)) as before,
  (2 * count_if(quality = 1 and stays) * 10000 + count_if(stays)) // (2 * nullif(count_if(stays), 0)) as after from marked group by source)
select source""", 1)


@query("decontam_delta", _LEAKED)
def decontam_delta(spark, d):
    """The share of labelled documents of good quality by source, before and after those with a leak go."""
    table = docs(spark, d)
    leaked = ngram_decontaminate(table.select(F.col("doc_id").alias("id"), "text"), read(spark, d, "benchmark"), 13).select("id").distinct().withColumn("gone", F.lit(True))
    marked = table.select("doc_id", "source").join(labels(spark, d), "doc_id").join(leaked, F.col("doc_id") == F.col("id"), "left")
    stays, good = F.col("gone").isNull(), F.col("quality") == 1
    counts = marked.groupBy("source").agg(F.count(F.lit(1)).alias("n"), F.count_if(good).alias("k"), F.count_if(stays).alias("m"), F.count_if(good & stays).alias("j"))
    wide = counts.select("source", M.half_up(F.col("k") * 10000, F.col("n")).alias("before"), F.when(F.col("m") > 0, M.half_up(F.col("j") * 10000, F.col("m"))).alias("after"))
    return wide.select("source", (F.col("after") - F.col("before")).alias("delta"), (F.col("after") < F.col("before")).alias("falls"))


_FUNNEL_ROWS = [(k, s, subject, n) for subject, *ns in P.FUNNEL for k, (s, n) in enumerate(zip(P.STAGES, ns, strict=True))]
_FUNNEL = P.values_sql(_FUNNEL_ROWS, "stage_no, stage, subject, n")


@query("stage_retention", f"""with f as (select * from {_FUNNEL} union all select stage_no, stage, 'total', sum(n) from {_FUNNEL} group by all),
b as (select *, lag(n) over (partition by subject order by stage_no) as before from f)
select subject, stage, n::bigint as n, ((2 * n * 10000 + before) // (2 * before))::bigint as kept from b where before > 0""")
def stage_retention(spark, d):
    rows = spark.createDataFrame(_FUNNEL_ROWS, "stage_no int, stage string, subject string, n long")
    total = rows.groupBy("stage_no", "stage").agg(F.sum("n").alias("n")).select("stage_no", "stage", F.lit("total").alias("subject"), "n")
    return M.stage_retention(rows.unionByName(total), "subject")


_EXTRACTION = P.values_sql(P.EXTRACTION, "subject, books, chunks, valid, high, low")


@query("published_valid_rate", f"select subject, ((2 * valid * 10000 + chunks) // (2 * chunks))::bigint as rate from {_EXTRACTION} union all select 'total', ((2 * sum(valid) * 10000 + sum(chunks)) // (2 * sum(chunks)))::bigint from {_EXTRACTION}")
def published_valid_rate(spark, d):
    rows = spark.createDataFrame(list(P.EXTRACTION), "subject string, books long, chunks long, valid long, high long, low long")
    total = rows.agg(F.sum("valid").alias("valid"), F.sum("chunks").alias("chunks")).select(F.lit("total").alias("subject"), "valid", "chunks")
    both = rows.select("subject", "valid", "chunks").unionByName(total)
    return both.select("subject", M.half_up(F.col("valid") * 10000, F.col("chunks")).alias("rate"))


_SELECTION = P.values_sql([(s, t, round(x[-1] * 100)) for s, t, *x in P.SELECTION], "source, strategy, cents")


@query("published_choice", f"select source, arg_max(strategy, cents) as best from {_SELECTION} group by source")
def published_choice(spark, d):
    """The strategy with the best overall score by source. For A keeping all scores best; the reference
    chose random among the matched sizes, which is next."""
    rows = spark.createDataFrame([(s, t, round(x[-1] * 100)) for s, t, *x in P.SELECTION], "source string, strategy string, cents long")
    return rows.groupBy("source").agg(F.max_by("strategy", "cents").alias("best"))


@query("published_matched_choice", f"select source, arg_max(strategy, cents) as best from {_SELECTION} where strategy <> 'all' group by source")
def published_matched_choice(spark, d):
    rows = spark.createDataFrame([(s, t, round(x[-1] * 100)) for s, t, *x in P.SELECTION if t != "all"], "source string, strategy string, cents long")
    return rows.groupBy("source").agg(F.max_by("strategy", "cents").alias("best"))


_MIXTURE = P.values_sql([(s, *(round(x * 10) for x in xs)) for s, *xs in P.MIXTURE], "source, raw, dedup, decontam, selected")


@query("published_mixture_total", f"select sum(raw)::bigint as raw, sum(dedup)::bigint as dedup, sum(decontam)::bigint as decontam, sum(selected)::bigint as selected from {_MIXTURE}")
def published_mixture_total(spark, d):
    rows = spark.createDataFrame([(s, *(round(x * 10) for x in xs)) for s, *xs in P.MIXTURE], "source string, raw long, dedup long, decontam long, selected long")
    return rows.agg(*[F.sum(c).alias(c) for c in ("raw", "dedup", "decontam", "selected")])


# ---- measures on responses --------------------------------------------------------------------


def _n(c: str) -> str:
    return f"len({words_sql(c)})"


@query("response_length", f"with {QA} select dataset, count(*) as n, round(avg({_n('answer')}), 6) as mean, round(var_samp({_n('answer')}), 4) as variance from qa group by dataset")
def response_length(spark, d):
    return M.response_length(qa(spark, d), "dataset")


@query("length_histogram", f"with b as (select lang, ({_n('text')} // 50)::int as bin from documents), c as (select lang, bin, count(*) as n from b group by all) select lang, bin, n, round(n / sum(n) over (partition by lang), 6)::double as share from c")
def length_histogram(spark, d):
    return M.length_histogram(docs(spark, d), "lang", "text")


@query("length_quantiles", "select lang, " + ", ".join(f"round(quantile_cont({_n('text')}, {p}), 6) as p{int(p * 100)}" for p in (0.25, 0.5, 0.75, 0.95)) + " from documents group by lang")
def length_quantiles(spark, d):
    return M.length_quantiles(docs(spark, d), "lang", "text")


_POINTS = f"points as (select source as name, round(avg({_n('text')}), 6) as length, round(avg(quality), 6) as score from documents join labels using (doc_id) group by source)"


def points(spark, d):
    return docs(spark, d).join(labels(spark, d), "doc_id").select("source", n_tokens("text").alias("t"), "quality").groupBy(F.col("source").alias("name")).agg(F.round(F.avg("t"), 6).alias("length"), F.round(F.avg("quality"), 6).alias("score"))


@query("length_score_corr", f"with {_POINTS} select count(*) as n, round(corr(length, score), 6) as corr from points")
def length_score_corr(spark, d):
    return M.length_score_corr(points(spark, d))


@query("pareto_front", f"with {_POINTS} select * from points p where not exists (select 1 from points q where q.length <= p.length and q.score >= p.score and (q.length < p.length or q.score > p.score))")
def pareto_front(spark, d):
    return M.pareto_front(points(spark, d))


@query("difficulty_histogram", f"{CHAIN} select floor(mean)::int as band, count(*) as n from means group by 1")
def difficulty_histogram(spark, d):
    return means(spark, d).groupBy(F.floor("mean").cast("int").alias("band")).agg(F.count(F.lit(1)).alias("n"))


_R = "list_transform(range(0, len(w) - 2), lambda i: array_to_string(list_slice(w, i + 1, i + 3), ' '))"


@query("repetition_rate", f"""with t as (select lang, {words_sql('text')} as w from documents)
select lang, count(*) as n, round(avg(case when len(w) >= 3 then 1 - len(list_distinct({_R}))::double / (len(w) - 2) else 0 end), 6) as repetition, round(avg((len(w) < 20)::int), 6) as short_share from t group by lang""")
def repetition_rate(spark, d):
    return M.repetition_rate(docs(spark, d), "lang", "text")


@query("length_difficulty_rank", f"""{CHAIN}, p as (select {_n('answer')} as length, mean from qa join means using (qid)),
r as (select *, rank() over (order by length) + (count(*) over (partition by length) - 1) / 2.0 as rl, rank() over (order by mean) + (count(*) over (partition by mean) - 1) / 2.0 as rm from p)
select count(*) as n, round(corr(length, mean), 6) as pearson, round(corr(rl, rm), 6) as spearman from r""")
def length_difficulty_rank(spark, d):
    rows = qa(spark, d).select("qid", n_tokens("answer").alias("length")).join(means(spark, d).select("qid", "mean"), "qid")
    return M.length_difficulty_rank(rows)


@query("call_budget", """with n as (select count(*) as n from documents) select unnest(['classify', 'extract', 'refine', 'gap', 'defects', 'judge', 'difficulty']) as stage,
unnest([n, 2 * n, n, n, n, 5 * n, 32 * n])::bigint as calls from n""")
def call_budget(spark, d):
    n = F.col("n")
    rows = docs(spark, d).agg(F.count(F.lit(1)).alias("n"))
    return M.call_budget({"classify": n, "extract": 2 * n, "refine": n, "gap": n, "defects": n, "judge": 5 * n, "difficulty": 32 * n}, rows)


@query("observed_calls", "select unnest(['defects', 'gap']) as role, unnest([count(distinct text), count(distinct text)])::bigint as calls from benchmark")
def observed_calls(spark, d):
    """Calls that a client was really asked for, by role: each distinct prompt once, although all runs twice."""
    from qacurate.models.clients import Model, TableClient, usage
    from qacurate.operators import refine
    from qacurate.staging import fresh_path

    items = read(spark, d, "benchmark").select(F.col("text").alias("question"), F.lit("It is so.").alias("answer"))
    cache = fresh_path(spark, "calls")
    for _ in range(2):
        model = Model(TableClient((), "no"), cache)
        refine.supplement(refine.flag_missing_reasoning(refine.judge_defects(items, model), model), model).count()
    return usage(spark, cache).select("role", "calls")
