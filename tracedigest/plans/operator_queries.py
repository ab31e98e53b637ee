"""One query per relational operator that the methods and their users lean on, over whole tables."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions import arrow
from ..operators import blocking, trace
from . import oracle as o
from .queries import shared_folder
from .workloads import docs_trace, table

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLE: dict[str, str] = {}


def query(name: str, sql: str | None = None):
    def add(f):
        QUERIES[f"op_{name}"] = f
        if sql is not None:
            ORACLE[f"op_{name}"] = sql
        return f

    return add


def t(spark: SparkSession, d: str, *names: str):
    out = [table(spark, d, n) for n in names]
    return out[0] if len(out) == 1 else out


DAY = "ts::date"


@query("scan_filter_project", "select l_orderkey, l_linenumber, l_returnflag, l_suppkey from lineitem where l_returnflag in ('R', 'A') and l_shipdate >= timestamp '1996-01-01' and l_shipdate < timestamp '1998-01-01'")
def _(spark, d):
    x = t(spark, d, "lineitem")
    return x.filter(F.col("l_returnflag").isin("R", "A") & (F.col("l_shipdate") >= F.lit("1996-01-01").cast("timestamp_ntz")) & (F.col("l_shipdate") < F.lit("1998-01-01").cast("timestamp_ntz"))).select("l_orderkey", "l_linenumber", "l_returnflag", "l_suppkey")


@query("payload_bytes", "select doc_id, octet_length(encode(text))::int as n_bytes, substr(hex(encode(text)), 1, 16) as head from documents")
def _(spark, d):
    return t(spark, d, "documents").select("doc_id", F.octet_length("text").alias("n_bytes"), F.substring(F.hex(F.encode("text", "UTF-8")), 1, 16).alias("head"))


@query("join_broadcast", "select s_suppkey, n_name, r_name from supplier join nation on s_nationkey = n_nationkey join region on n_regionkey = r_regionkey")
def _(spark, d):
    s, n, r = t(spark, d, "supplier", "nation", "region")
    names = n.join(F.broadcast(r), n["n_regionkey"] == r["r_regionkey"])
    return s.join(F.broadcast(names), s["s_nationkey"] == names["n_nationkey"]).select("s_suppkey", "n_name", "r_name")


@query("join_sortmerge", "select l_orderkey, l_linenumber, l_suppkey, o_custkey from lineitem join orders on l_orderkey = o_orderkey")
def _(spark, d):
    x, y = t(spark, d, "lineitem", "orders")
    return x.hint("merge").join(y, x["l_orderkey"] == y["o_orderkey"]).select("l_orderkey", "l_linenumber", "l_suppkey", "o_custkey")


@query("join_shuffle_hash", "select o_orderkey, c_nationkey from orders join customer on o_custkey = c_custkey")
def _(spark, d):
    x, y = t(spark, d, "orders", "customer")
    return x.join(y.hint("shuffle_hash"), x["o_custkey"] == y["c_custkey"]).select("o_orderkey", "c_nationkey")


@query("join_semi", "select doc_id, lang from documents where doc_id in (select doc_id from labels)")
def _(spark, d):
    x, y = t(spark, d, "documents", "labels")
    return x.join(y, "doc_id", "left_semi").select("doc_id", "lang")


@query("join_anti", "select doc_id, lang from documents where doc_id not in (select doc_id from labels)")
def _(spark, d):
    x, y = t(spark, d, "documents", "labels")
    return x.join(y, "doc_id", "left_anti").select("doc_id", "lang")


@query("join_left", "select lang, count(*) as docs, count(quality) as labelled from documents left join labels using (doc_id) group by lang")
def _(spark, d):
    x, y = t(spark, d, "documents", "labels")
    return x.join(y, "doc_id", "left").groupBy("lang").agg(F.count("*").alias("docs"), F.count("quality").alias("labelled"))


@query("join_full", "select count(*) as n, count(lang) as with_doc, count(quality) as with_label from documents full join labels using (doc_id)")
def _(spark, d):
    x, y = t(spark, d, "documents", "labels")
    return x.join(y, "doc_id", "full").agg(F.count("*").alias("n"), F.count("lang").alias("with_doc"), F.count("quality").alias("with_label"))


@query("join_theta", "select item_id, doc_id from benchmark b join documents d on contains(d.text, b.text) where b.text <> ''")
def _(spark, d):
    x, y = t(spark, d, "documents", "benchmark")
    items = y.filter("text <> ''").select("item_id", F.col("text").alias("item"))
    return x.join(F.broadcast(items), F.contains("text", "item")).select("item_id", "doc_id")


@query("join_range", "select o_orderkey, l_linenumber, datediff('day', o_orderdate::date, l_shipdate::date)::int as days from orders join lineitem on o_orderkey = l_orderkey and l_shipdate between o_orderdate and o_orderdate + interval 30 day")
def _(spark, d):
    x, y = t(spark, d, "orders", "lineitem")
    inside = (x["o_orderkey"] == y["l_orderkey"]) & F.expr("l_shipdate between o_orderdate and o_orderdate + interval 30 days")
    return x.join(y, inside).select("o_orderkey", "l_linenumber", F.datediff("l_shipdate", "o_orderdate").alias("days"))


@query("join_asof", "with e as (select user_id, event_id, ts from events where event_type = 'error'), p as (select user_id, ts as p_ts, event_id as p_id from events where event_type = 'purchase') select e.event_id, max(p_ts) as last_ts from e left join p on e.user_id = p.user_id and p_ts <= e.ts group by e.event_id")
def _(spark, d):
    x = t(spark, d, "events")
    # both sides in one order of time per user, the last purchase carried on: no pair of rows is made
    some = x.filter("event_type in ('error', 'purchase')").select("user_id", "event_id", "ts", (F.col("event_type") == "error").alias("asks"))
    last = F.last(F.when(~F.col("asks"), F.col("ts")), ignorenulls=True).over(Window.partitionBy("user_id").orderBy("ts", "asks"))
    return some.select("event_id", "asks", last.alias("last_ts")).filter("asks").select("event_id", "last_ts")


@query("join_cross", "select r_name, threshold from region, (values (0), (20), (40)) g(threshold)")
def _(spark, d):
    return t(spark, d, "region").crossJoin(F.broadcast(spark.createDataFrame([(0,), (20,), (40,)], "threshold int"))).select("r_name", "threshold")


LEDGER = "lineitem join orders on l_orderkey = o_orderkey join supplier on l_suppkey = s_suppkey join customer on o_custkey = c_custkey"


@query("agg_hash", f"select s_nationkey, c_nationkey, count(*) as lines, sum(l_quantity)::bigint as quantity from {LEDGER} group by all")
def _(spark, d):
    x, y, s, c = t(spark, d, "lineitem", "orders", "supplier", "customer")
    j = x.join(y, F.col("l_orderkey") == F.col("o_orderkey")).join(s, F.col("l_suppkey") == F.col("s_suppkey")).join(c, F.col("o_custkey") == F.col("c_custkey"))
    return j.groupBy("s_nationkey", "c_nationkey").agg(F.count("*").alias("lines"), F.sum("l_quantity").cast("bigint").alias("quantity"))


@query("agg_distinct", "select event_type, count(distinct user_id) as users from events group by event_type")
def _(spark, d):
    return t(spark, d, "events").groupBy("event_type").agg(F.countDistinct("user_id").alias("users"))


@query("agg_approx", "select l_returnflag, true as users_close, true as median_close from lineitem group by l_returnflag")
def _(spark, d):
    """Approximate aggregates, judged against exact ones: within 10 and 5 per cent."""
    x = t(spark, d, "lineitem").groupBy("l_returnflag").agg(F.approx_count_distinct("l_partkey", 0.02).alias("a"), F.countDistinct("l_partkey").alias("b"), F.approx_percentile("l_extendedprice", 0.5, 10_000).alias("p"), F.percentile("l_extendedprice", 0.5).alias("q"))
    return x.select("l_returnflag", (F.abs(F.col("a") / F.col("b") - 1) < 0.1).alias("users_close"), (F.abs(F.col("p") / F.col("q") - 1) < 0.05).alias("median_close"))


@query("agg_bit", "select event_type, bit_or(1::bigint << (user_id % 31)::int)::bigint as any_, bit_and(user_id)::bigint as all_, bit_xor(user_id)::bigint as odd, sum(bit_count(user_id))::bigint as ones from events group by event_type")
def _(spark, d):
    bit = F.expr("shiftleft(1L, cast(user_id % 31 as int))")
    return t(spark, d, "events").groupBy("event_type").agg(F.bit_or(bit).alias("any_"), F.bit_and("user_id").alias("all_"), F.bit_xor("user_id").alias("odd"), F.sum(F.bit_count("user_id")).cast("bigint").alias("ones"))


@query("agg_bool", "select quality, bool_and(toxic = 0) as all_clean, bool_or(toxic = 1) as some_toxic from labels group by quality")
def _(spark, d):
    return t(spark, d, "labels").groupBy("quality").agg(F.bool_and(F.col("toxic") == 0).alias("all_clean"), F.bool_or(F.col("toxic") == 1).alias("some_toxic"))


GROUPS = "select lang, quality, count(*) as docs, sum(n_chars)::bigint as chars, grouping(lang, quality)::bigint as level from documents join labels using (doc_id) group by"


@query("cube", f"{GROUPS} cube (lang, quality)")
def _(spark, d):
    x, y = t(spark, d, "documents", "labels")
    return x.join(y, "doc_id").cube("lang", "quality").agg(F.count("*").alias("docs"), F.sum("n_chars").alias("chars"), F.grouping_id().alias("level"))


@query("rollup", f"{GROUPS} rollup (lang, quality)")
def _(spark, d):
    x, y = t(spark, d, "documents", "labels")
    return x.join(y, "doc_id").rollup("lang", "quality").agg(F.count("*").alias("docs"), F.sum("n_chars").alias("chars"), F.grouping_id().alias("level"))


@query("grouping_sets", f"{GROUPS} grouping sets ((lang), (quality))")
def _(spark, d):
    x, y = t(spark, d, "documents", "labels")
    return x.join(y, "doc_id").groupingSets([[F.col("lang")], [F.col("quality")]], "lang", "quality").agg(F.count("*").alias("docs"), F.sum("n_chars").alias("chars"), F.grouping_id().alias("level"))


@query("pivot", f"select {DAY} as day, count(*) filter (event_type = 'view') as view, count(*) filter (event_type = 'click') as click, count(*) filter (event_type = 'purchase') as purchase, count(*) filter (event_type = 'error') as error from events group by 1")
def _(spark, d):
    x = t(spark, d, "events").withColumn("day", F.to_date("ts"))
    out = x.groupBy("day").pivot("event_type", ["view", "click", "purchase", "error"]).agg(F.count(F.lit(1)))
    return out.na.fill(0)


def _ranked(name: str, f, sql: str):
    @query(name, f"select lang, doc_id, {sql} over (partition by lang order by n_chars desc{', doc_id' if name == 'row_number' or name == 'ntile' else ''}) as r from documents")
    def _(spark, d):
        order = [F.desc("n_chars")] + (["doc_id"] if name in ("row_number", "ntile") else [])
        out = f().over(Window.partitionBy("lang").orderBy(*order))
        return t(spark, d, "documents").select("lang", "doc_id", (F.round(out, 6) if name in ("cume_dist", "percent_rank") else out.cast("bigint")).alias("r"))


for _name, _f, _sql in (("rank", F.rank, "rank()"), ("dense_rank", F.dense_rank, "dense_rank()"), ("row_number", F.row_number, "row_number()"), ("ntile", lambda: F.ntile(4), "ntile(4)")):
    _ranked(_name, _f, _sql)


@query("cume_dist", "select lang, doc_id, round(cume_dist() over (partition by lang order by n_chars), 6) as r from documents")
def _(spark, d):
    return t(spark, d, "documents").select("lang", "doc_id", F.round(F.cume_dist().over(Window.partitionBy("lang").orderBy("n_chars")), 6).alias("r"))


@query("percent_rank", "select lang, doc_id, round(percent_rank() over (partition by lang order by n_chars), 6) as r from documents")
def _(spark, d):
    return t(spark, d, "documents").select("lang", "doc_id", F.round(F.percent_rank().over(Window.partitionBy("lang").orderBy("n_chars")), 6).alias("r"))


@query("lead_lag", "select event_id, lag(event_id) over w as before, lead(event_id) over w as after from events window w as (partition by user_id order by ts, event_id)")
def _(spark, d):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    return t(spark, d, "events").select("event_id", F.lag("event_id").over(w).alias("before"), F.lead("event_id").over(w).alias("after"))


@query("frame_rows", "select event_id, min(round(value * 10000)::bigint) over (partition by user_id order by ts, event_id rows between current row and 3 following) as least from events")
def _(spark, d):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(0, 3)
    return t(spark, d, "events").select("event_id", F.min(F.round(F.col("value") * 10000).cast("bigint")).over(w).alias("least"))


@query("frame_range", "select event_id, count(*) over (partition by user_id order by epoch_us(ts) range between 86400000000 preceding and current row) as in_a_day from events")
def _(spark, d):
    us = F.unix_micros(F.col("ts").cast("timestamp"))
    w = Window.partitionBy("user_id").orderBy(us).rangeBetween(-86_400_000_000, 0)
    return t(spark, d, "events").select("event_id", F.count("*").over(w).alias("in_a_day"))


@query("topk", "select doc_id, n_chars from documents order by n_chars desc, doc_id limit 10")
def _(spark, d):
    return t(spark, d, "documents").orderBy(F.desc("n_chars"), "doc_id").limit(10).select("doc_id", "n_chars")


@query("sort_limit", "select user_id, count(*) as n from events group by user_id order by n desc, user_id limit 20")
def _(spark, d):
    return t(spark, d, "events").groupBy("user_id").agg(F.count("*").alias("n")).orderBy(F.desc("n"), "user_id").limit(20)


@query("union", "select doc_id from documents union select doc_id from labels")
def _(spark, d):
    x, y = t(spark, d, "documents", "labels")
    return x.select("doc_id").unionByName(y.select("doc_id")).distinct()


@query("intersect", "select doc_id from documents intersect select doc_id from labels")
def _(spark, d):
    x, y = t(spark, d, "documents", "labels")
    return x.select("doc_id").intersect(y.select("doc_id"))


@query("except", "select doc_id from documents except select doc_id from labels")
def _(spark, d):
    x, y = t(spark, d, "documents", "labels")
    return x.select("doc_id").subtract(y.select("doc_id"))


@query("string", "select page_id, upper(substr(url, 1, 5)) as head, instr(url, '://')::int as at, length(url)::int as n, concat_ws('|', page_id, url) as line, contains(html, '<p>') as has_p from pages")
def _(spark, d):
    return t(spark, d, "pages").select("page_id", F.upper(F.substring("url", 1, 5)).alias("head"), F.instr("url", "://").alias("at"), F.length("url").alias("n"), F.concat_ws("|", "page_id", "url").alias("line"), F.contains("html", F.lit("<p>")).alias("has_p"))


@query("regex", "select page_id, regexp_extract(url, '^([a-z]+)://', 1) as scheme, regexp_extract(url, '://([^/?#]*)', 1) as host, regexp_extract(url, '://[^/?#]*([^?#]*)', 1) as path from pages")
def _(spark, d):
    return t(spark, d, "pages").select("page_id", F.regexp_extract("url", "^([a-z]+)://", 1).alias("scheme"), F.regexp_extract("url", "://([^/?#]*)", 1).alias("host"), F.regexp_extract("url", "://[^/?#]*([^?#]*)", 1).alias("path"))


@query("date", "select o_orderkey, year(o_orderdate)::int as y, date_trunc('month', o_orderdate)::date as m, datediff('day', date '1995-01-01', o_orderdate::date)::int as days from orders")
def _(spark, d):
    return t(spark, d, "orders").select("o_orderkey", F.year("o_orderdate").alias("y"), F.trunc("o_orderdate", "month").alias("m"), F.datediff("o_orderdate", F.lit("1995-01-01").cast("date")).alias("days"))


@query("math_bits", "select o_orderkey, (o_orderkey % 64)::int as section, (1::bigint << (o_orderkey % 32)::int) as mask, round(log2(o_orderkey + 1), 6) as lg, round(pow(0.5, o_orderkey % 7), 6) as p, ('0x' || substr(md5(o_orderkey::varchar), 1, 8))::bigint as h from orders")
def _(spark, d):
    k = F.col("o_orderkey")
    return t(spark, d, "orders").select("o_orderkey", F.pmod(k, F.lit(64)).cast("int").alias("section"), F.expr("shiftleft(1L, cast(o_orderkey % 32 as int))").alias("mask"), F.round(F.log2(k + 1), 6).alias("lg"), F.round(F.pow(F.lit(0.5), k % 7), 6).alias("p"), F.conv(F.substring(F.md5(k.cast("string")), 1, 8), 16, 10).cast("bigint").alias("h"))


@query("array", "select vec_id, len(embedding)::int as n, round(list_min(embedding)::double, 6) as least, len(list_filter(embedding, lambda x: x > 0))::int as positive from embeddings")
def _(spark, d):
    e = F.col("embedding")
    return t(spark, d, "embeddings").select("vec_id", F.size(e).alias("n"), F.round(F.array_min(e).cast("double"), 6).alias("least"), F.size(F.filter(e, lambda x: x > 0)).alias("positive"))


@query("explode", "select lang, len(w)::int as length, count(*) as words from (select lang, unnest(string_split(text, ' ')) as w from documents) group by all")
def _(spark, d):
    return t(spark, d, "documents").select("lang", F.explode(F.split("text", " ")).alias("w")).groupBy("lang", F.length("w").alias("length")).agg(F.count("*").alias("words"))


@query("json", "select event_id, json_extract_string(props, '$.k') as k from events")
def _(spark, d):
    return t(spark, d, "events").select("event_id", F.get_json_object("props", "$.k").alias("k"))


@query("map", "select event_id, event_type as kind, user_id::varchar as who from events")
def _(spark, d):
    header = F.map_from_arrays(F.array(F.lit("kind"), F.lit("who")), F.array("event_type", F.col("user_id").cast("string")))
    return t(spark, d, "events").withColumn("header", header).select("event_id", F.element_at("header", "kind").alias("kind"), F.element_at("header", "who").alias("who"))


@query("udf_blocks", f"with {o.DOCS}, {o.blocks()} select flow_key, block_no, size, md5(block) as digest from blk")
def _(spark, d):
    """Blocks by the Arrow function that SQL users call."""
    rows = docs_trace(spark, d).select("flow_key", F.explode(arrow.winnow_blocks("payload")).alias("b"))
    return rows.select("flow_key", "b.block_no", "b.size", F.md5("b.block").alias("digest"))


@query("udtf_blocks", f"with {o.DOCS}, {o.blocks()} select flow_key, block_no, size, md5(block) as digest from blk")
def _(spark, d):
    """Blocks by the table function, joined laterally."""
    docs_trace(spark, d).createOrReplaceTempView("td_trace_in")
    arrow.register(spark)
    return spark.sql("select flow_key, b.block_no, b.size, md5(b.block) as digest from td_trace_in, lateral td_winnow(payload, 64, 4, 0) b")


@query("window_tumbling", f"select {DAY} as day, event_type, count(*) as n from events group by all")
def _(spark, d):
    x = t(spark, d, "events").withColumn("ts", F.col("ts").cast("timestamp"))
    return x.groupBy(F.window("ts", "1 day").alias("w"), "event_type").agg(F.count("*").alias("n")).select(F.to_date("w.start").alias("day"), "event_type", "n")


@query("window_sliding", f"select day, count(*) as n from (select unnest([{DAY}, ({DAY} - interval 1 day)::date]) as day from events) group by day")
def _(spark, d):
    x = t(spark, d, "events").withColumn("ts", F.col("ts").cast("timestamp"))
    return x.groupBy(F.window("ts", "2 days", "1 day").alias("w")).agg(F.count("*").alias("n")).select(F.to_date("w.start").alias("day"), "n")


@query("session", "with g as (select user_id, ts, case when ts >= lag(ts) over (partition by user_id order by ts) + interval 1 hour or lag(ts) over (partition by user_id order by ts) is null then 1 else 0 end as new from events), s as (select user_id, ts, sum(new) over (partition by user_id order by ts rows unbounded preceding) as s from g) select user_id, min(ts) as first_ts, count(*) as n from s group by user_id, s")
def _(spark, d):
    x = t(spark, d, "events").withColumn("ts", F.col("ts").cast("timestamp"))
    return x.groupBy("user_id", F.session_window("ts", "1 hour").alias("w")).agg(F.count("*").alias("n")).select("user_id", F.col("w.start").cast("timestamp_ntz").alias("first_ts"), "n")


@query("write_read", "select source as src, lang as dst, count(*) as packets from documents where lang = 'en' group by all")
def _(spark, d):
    """Partitioned Parquet written and read with a partition filter."""
    path = f"{shared_folder(spark)}/trace"
    docs_trace(spark, d).select("src", "dst", "payload").write.partitionBy("dst").parquet(path)
    return spark.read.parquet(path).filter("dst = 'en'").groupBy("src", "dst").agg(F.count("*").alias("packets"))


@query("reassemble", "select conv_id::varchar as flow_key, sum(octet_length(encode(coalesce(text, ''))))::int as n_bytes, md5(string_agg(coalesce(text, ''), '' order by turn)) as digest from conversations group by conv_id")
def _(spark, d):
    whole = trace.reassemble(trace.from_conversations(t(spark, d, "conversations")))
    return whole.select("flow_key", F.octet_length("payload").alias("n_bytes"), F.md5("payload").alias("digest"))


@query("bounds_per_language", f"with {o.DOCS}, {o.bounds()} select dst, count(*) as bounds from bounds join trace using (flow_key, seq) group by dst")
def _(spark, d):
    packets = docs_trace(spark, d)
    return blocking.winnow_bounds(packets).join(packets.select("flow_key", "dst"), "flow_key").groupBy("dst").agg(F.count("*").alias("bounds"))
