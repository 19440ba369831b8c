"""Sources, sinks and user-defined functions."""

from __future__ import annotations

from pyspark.sql import functions as F

from qacurate.functions import udfs
from qacurate.queries.common import TURNS_SQL, docs, turns, words_sql
from qacurate.registry import query, read
from qacurate.sources import tables as T
from qacurate.staging import fresh_path


@query("scan_parquet", "select doc_id, lang from documents where n_chars > 500")
def scan_parquet(spark, d):
    return docs(spark, d).where("n_chars > 500").select("doc_id", "lang")


def _trip(name, fmt, table, columns, **options):
    @query(name, f"select {columns} from {table}")
    def run(spark, d):
        return T.round_trip(read(spark, d, table).select(*columns.split(", ")), fmt, **options)


_trip("scan_csv_roundtrip", "csv", "customer", "c_custkey, c_name, c_nationkey, c_mktsegment", header="true")
_trip("scan_json_roundtrip", "json", "documents", "doc_id, text, lang")
_trip("scan_orc_roundtrip", "orc", "supplier", "s_suppkey, s_name, s_nationkey")


@query("scan_text_lines", "select count(*) as n, sum(length(line))::bigint as chars from (select unnest(string_split(text, chr(10))) as line from documents)")
def scan_text_lines(spark, d):
    path = fresh_path(spark, "lines")
    docs(spark, d).select(F.explode(F.split("text", "\n", -1)).alias("value")).write.text(path)
    return spark.read.text(path).agg(F.count(F.lit(1)).alias("n"), F.sum(F.length("value")).cast("long").alias("chars"))


@query("scan_partitioned", "select doc_id, source from documents where lang = 'fr'")
def scan_partitioned(spark, d):
    path = T.write_partitioned(docs(spark, d).select("doc_id", "source", "lang"), "lang")
    return spark.read.parquet(path).where("lang = 'fr'").select("doc_id", "source")


@query("scan_binary", "select count(*) as n, sum(octet_length(encode(coalesce(html, ''))))::bigint as bytes from pages")
def scan_binary(spark, d):
    """Files read as whole blobs: one per page, each a single text record."""
    path = fresh_path(spark, "blobs")
    p = read(spark, d, "pages").select("page_id", F.coalesce("html", F.lit("")).alias("value"))
    p.repartition(4).select("value").write.option("lineSep", "\x00").text(path)
    blobs = spark.read.format("binaryFile").option("pathGlobFilter", "*.txt").load(path)
    ends = F.size(F.split(F.col("content").cast("string"), "\x00", -1)) - 1
    return blobs.agg(F.sum(ends).cast("long").alias("n"), F.sum(F.col("length") - ends).cast("long").alias("bytes"))


@query("sink_roundtrip", "select true as same, count(*) as n from documents")
def sink_roundtrip(spark, d):
    t = docs(spark, d)
    path = fresh_path(spark, "sink")
    t.write.option("maxRecordsPerFile", 500).parquet(path)
    a = T.manifest(t, ["doc_id", "text"]).select("n", F.col("digest").alias("da"))
    b = T.manifest(spark.read.parquet(path), ["doc_id", "text"]).select(F.col("n").alias("m"), F.col("digest").alias("db"))
    return a.join(b).select((F.col("da").eqNullSafe(F.col("db")) & (F.col("n") == F.col("m"))).alias("same"), "n")


@query("sink_bucketed", "select count(*) as n from documents join labels using (doc_id)")
def sink_bucketed(spark, d):
    """Two tables bucketed alike join without a shuffle."""
    for name in ("documents", "labels"):
        read(spark, d, name).select("doc_id").write.mode("overwrite").format("parquet").bucketBy(8, "doc_id").sortBy("doc_id").option("path", fresh_path(spark, f"bucket-{name}")).saveAsTable(f"qacurate_bucket_{name}")
    return spark.table("qacurate_bucket_documents").join(spark.table("qacurate_bucket_labels"), "doc_id").agg(F.count(F.lit(1)).alias("n"))


@query("chat_source", f"with t as ({TURNS_SQL}) select qid, 0 as turn, 'user' as role, question as content from t union all select qid, 1, 'assistant', answer from t")
def chat_source(spark, d):
    """The chat source's reader over the conversations' records, in Spark's tasks."""
    turn = lambda role, c: F.struct(F.lit(role).alias("role"), F.col(c).alias("content"))
    records = turns(spark, d).select(F.to_json(F.struct("qid", F.array(turn("user", "question"), turn("assistant", "answer")).alias("messages"))).alias("record"))
    return T.read_records(records)


@query("chat_roundtrip", f"with t as ({TURNS_SQL}) select qid, 0 as turn, 'user' as role, question as content from t union all select qid, 1, 'assistant', answer from t")
def chat_roundtrip(spark, d):
    path = fresh_path(spark, "chat")
    turn = lambda role, c: F.struct(F.lit(role).alias("role"), F.col(c).alias("content"))
    turns(spark, d).select("qid", F.array(turn("user", "question"), turn("assistant", "answer")).alias("messages")).write.json(path)
    return T.read_chat(spark, path)


@query("call_model_cached", "select count(*) as n, 2 as calls_of_answers from benchmark")
def call_model_cached(spark, d):
    """Every item asked twice through one cache: the second call finds all its answers."""
    from qacurate.models.clients import EchoClient, ReplayClient, call_model, prompt

    cache = fresh_path(spark, "cache")
    b = read(spark, d, "benchmark")
    first = call_model(b, "classify", prompt("classify"), EchoClient(), cache, "a1")
    second = call_model(first, "classify", prompt("classify"), ReplayClient("echo-1"), cache, "a2")
    return second.where("a1 = a2 and a1 is not null").agg(F.count(F.lit(1)).alias("n"), F.lit(2).alias("calls_of_answers"))


@query("udf_pandas_unwrap", "select item_id, 'x{' || item_id || '{y}}' as inside from benchmark")
def udf_pandas_unwrap(spark, d):
    text = F.concat(F.lit("So \\boxed{x{"), F.col("item_id").cast("string"), F.lit("{y}}} holds"))
    return read(spark, d, "benchmark").select("item_id", udfs.unwrap_balanced(text).alias("inside"))


@query("udtf_chunks", r"select doc_id, i::int as chunk_no, len(list_slice(w, i * 100 + 1, i * 100 + 100))::int as n_tokens from (select doc_id, regexp_extract_all(text, '[^ \t\n\r]+') as w from documents) t, unnest(range(0, ceil(len(w) / 100.0)::bigint)) as u(i)")
def udtf_chunks(spark, d):
    udfs.register_all(spark)
    docs(spark, d).select("doc_id", "text").createOrReplaceTempView("_udtf_docs")
    return spark.sql("select doc_id, c.chunk_no, c.n_tokens from _udtf_docs, lateral chunk_text(text, 100) c")


@query("udaf_weighted", "select l_returnflag, round(sum(l_discount * l_quantity) / sum(l_quantity), 6) as mean from lineitem group by all")
def udaf_weighted(spark, d):
    li = read(spark, d, "lineitem")
    part = li.groupBy("l_returnflag", (F.col("l_orderkey") % 64).alias("k")).agg(F.sum(F.col("l_discount") * F.col("l_quantity")).alias("x"), F.sum("l_quantity").alias("w"))
    return part.groupBy("l_returnflag").agg(F.round(udfs.weighted_mean(F.col("x") / F.col("w"), F.col("w")), 6).alias("mean"))


_X = f"list_distinct({words_sql('a.text')})"
_Y = f"list_distinct({words_sql('b.text')})"


@query("sql_udf_jaccard", f"select a.item_id as a, b.item_id as b, round(len(list_intersect({_X}, {_Y}))::double / (len({_X}) + len({_Y}) - len(list_intersect({_X}, {_Y}))), 6) as j from benchmark a join benchmark b on b.item_id = a.item_id + 1")
def sql_udf_jaccard(spark, d):
    from qacurate.functions.text import tokens

    udfs.register_all(spark)
    read(spark, d, "benchmark").select("item_id", tokens("text").alias("w")).createOrReplaceTempView("_udf_items")
    return spark.sql("select a.item_id as a, b.item_id as b, round(set_jaccard(a.w, b.w), 6) as j from _udf_items a join _udf_items b on b.item_id = a.item_id + 1")
