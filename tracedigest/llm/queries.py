"""The ten operators' queries over whole tables, and their SQL where SQL can say it."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import bin_packing, decontaminate, histogram_shard, language_id, preference_format, probminhash, secret_scan, substring_dedup, url_filter, vamana


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def op1_substring_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = substring_dedup.dedup(table(spark, sf_dir, "documents"))
    return out.select("doc_id", "n_words", "n_removed", F.sha2("kept", 256).alias("kept_sha256"))


def op2_url_filter(spark: SparkSession, sf_dir: str) -> DataFrame:
    return url_filter.judge(table(spark, sf_dir, "pages")).select("page_id", "host", "path", "rule", "verdict")


def op3_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    held = language_id.held_out()
    out = language_id.predict(docs, language_id.train(docs.filter(~held)))
    return out.select("doc_id", held.alias("held_out"), "lang_pred", "score")


def op4_graph_neighbours(spark: SparkSession, sf_dir: str) -> DataFrame:
    return vamana.nearest(table(spark, sf_dir, "embeddings"))


def op5_decontaminate(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = decontaminate.hits(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))
    return out.select("doc_id", "n_words", "n_hit", F.size("items").cast("long").alias("n_items"), F.sha2(F.array_join("items", ","), 256).alias("items_sha256"), "contaminated")


def op6_secret_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    out = secret_scan.scan(docs, repo=F.concat_ws("/", "source", "lang"), owner=F.col("source"))
    count = lambda k: F.size(F.filter("base", lambda x: x["k"] == k)).cast("long")
    return out.select(
        "doc_id", count(0).alias("n_assign"), count(1).alias("n_access"), count(2).alias("n_hex"),
        F.sha2(secret_scan.shown(F.col("base")), 256).alias("base_sha256"), secret_scan.shown(F.col("spans")).alias("spans"),
        F.col("n_live").cast("long").alias("n_live"), F.col("n_example").cast("long").alias("n_example"),
    )


def op7_best_fit_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return bin_packing.pack_documents(table(spark, sf_dir, "documents"))


def op8_histogram_shards(spark: SparkSession, sf_dir: str) -> DataFrame:
    return histogram_shard.histogram_shards(table(spark, sf_dir, "documents")).drop("key")


def op9_preference_format(spark: SparkSession, sf_dir: str) -> DataFrame:
    pairs = preference_format.swapped_reply_pairs(table(spark, sf_dir, "conversations"))
    out = preference_format.format_pairs(pairs)
    spans = lambda c: F.array_join(F.transform(c, lambda x: F.concat_ws("-", x["a"].cast("string"), x["b"].cast("string"))), ",")
    return out.select("pair_id", "n_prefix", "prompt", "chosen", "rejected", spans("chosen_mask").alias("chosen_mask"), spans("rejected_mask").alias("rejected_mask"))


def op10_probminhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    return probminhash.dedup(table(spark, sf_dir, "documents")).select("doc_id", "class_id")


QUERIES = {
    f.__name__: f
    for f in (
        op1_substring_dedup, op2_url_filter, op3_language_id, op4_graph_neighbours, op5_decontaminate, op6_secret_scan,
        op7_best_fit_packing, op8_histogram_shards, op9_preference_format, op10_probminhash,
    )
}

def _secret_sql() -> str:
    """Matches of each kind with their places (from the pieces between them), owners of each value, and what follows from both."""
    words = "|".join("".join(f"[{c.upper()}{c}]" if c.isalpha() else c for c in w) for w in ("password", "passwd", "secret", "token", "api_?key"))
    patterns = [(f"""({words})["\']?\\x20*[:=]\\x20*["\']?([A-Za-z0-9+/_.=-]+)""", 2)] + [(secret_scan.KINDS[k][0], 0) for k in ("access", "hex", "format")]
    quoted = [(p.replace("'", "''"), g) for p, g in patterns]
    least = [secret_scan.KINDS[k][2] for k in secret_scan.KINDS]
    found = " union all ".join(f"select doc_id, owner, repo, {n} as k, {least[n]} as least_, string_split_regex(text, '{p}') as g, regexp_extract_all(text, '{p}') as w, regexp_extract_all(text, '{p}', {g}) as v from t where regexp_matches(text, '{p}')" for n, (p, g) in enumerate(quoted))
    return f"""
with t as (select doc_id, coalesce(text, '') as text, coalesce(source, chr(1)) as owner, concat_ws('/', source, lang) as repo from documents),
m as ({found}),
x as (select doc_id, owner, repo, k, least_, w[i] as whole, v[i] as val, list_sum(list_transform(g[1:i], lambda y: length(y))) + coalesce(list_sum(list_transform(w[1:i - 1], lambda y: length(y))), 0) as s from (select *, unnest(range(1, len(w) + 1)) as i from m)),
c as (select distinct doc_id, owner, repo, k, s::bigint as s, (s + length(whole))::bigint as e, val from x where length(val) >= least_),
o as (select val, count(distinct owner) = 1 and count(distinct owner || chr(2) || repo) <= {secret_scan.MOST_REPOS} as live from c group by val),
y as (select c.*, live, ['assign', 'access', 'hex', 'format'][k + 1] || ':' || s || ':' || e as shown from c join o using (val)),
a as (select doc_id, count(*) filter (k = 0) as n_assign, count(*) filter (k = 1) as n_access, count(*) filter (k = 2) as n_hex, coalesce(string_agg(shown, ',' order by s, k) filter (k < 3), '') as base,
  coalesce(string_agg(shown, ',' order by s, k) filter (k < 3 or live), '') as spans, count(*) filter (live) as n_live, count(*) filter (not live) as n_example from y group by doc_id)
select t.doc_id, coalesce(n_assign, 0)::bigint as n_assign, coalesce(n_access, 0)::bigint as n_access, coalesce(n_hex, 0)::bigint as n_hex, sha256(coalesce(base, '')) as base_sha256, coalesce(spans, '') as spans, coalesce(n_live, 0)::bigint as n_live, coalesce(n_example, 0)::bigint as n_example
from t left join a using (doc_id)"""


#: DuckDB SQL for the operators that SQL can say.
ORACLE_SQL = {
    "op6_secret_scan": _secret_sql(),
    "op1_substring_dedup": r"""
with t as (select doc_id, regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+') as w from documents),
x as (select doc_id, i, hash(array_to_string(w[i : i + 12], ' ')) as h1, md5(array_to_string(w[i : i + 12], ' ')) as h2 from (select doc_id, w, unnest(range(1, len(w) - 11)) as i from t)),
least as (select h1, h2, min(doc_id) as first from x group by h1, h2),
gone as (select distinct doc_id, i + k as p from x join least using (h1, h2), range(13) r(k) where first < doc_id),
words as (select doc_id, unnest(w) as word, unnest(range(1, len(w) + 1)) as p from t),
kept as (select words.doc_id, string_agg(word, ' ' order by words.p) filter (gone.p is null) as k, count(gone.p) as n_removed from words left join gone on words.doc_id = gone.doc_id and words.p = gone.p group by words.doc_id)
select doc_id, len(w)::bigint as n_words, coalesce(n_removed, 0)::bigint as n_removed, sha256(coalesce(k, '')) as kept_sha256 from t left join kept using (doc_id)""",
    "op2_url_filter": r"""
with p as (select page_id, case when instr(url, '://') > 0 then substr(url, instr(url, '://') + 3) else '' end as rest from pages),
q as (select page_id, translate(coalesce(regexp_extract(rest, '^([^/?#]*)', 1, 's'), ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') as host,
      coalesce(regexp_extract(rest, '^[^/?#]*([^?#]*)', 1, 's'), '') as path from p),
r(verdict, rule, h, s) as (values ('allow', 'com/', 'com', '/'), ('block', 'example.com/en/', 'example.com', '/en/'), ('allow', 'www.example.com/en/', 'www.example.com', '/en/'),
      ('block', 'net/es/', 'net', '/es/'), ('block', 'net/fr/', 'net', '/fr/')),
f as (select page_id, arg_max(rule, length(rule)) as rule, arg_max(r.verdict, length(rule)) as verdict
      from q join r on (host = h or ends_with(host, '.' || h)) and starts_with(path, s) group by page_id)
select q.page_id, host, path, f.rule, coalesce(f.verdict, case when regexp_matches(host, '(^|[.-])(ads-track|adserver|betting|bets|bingo|casino|cheap-pills|click-bait|crack-keys|dating-now|doubleclick|escorts|free-money|jackpot|keygen|link-farm|lottery|payday-loan|pharmacy-online|phishing|poker|porn|replica-watches|slots|spam-farm|sportsbook|torrents|viagra|warez|win-prize|xxx)($|[.-])')
  or regexp_matches(path, '(^|[/._-])(casino|escorts|payday-loan|poker|porn|viagra|warez|xxx)($|[/._-])') then 'block' else 'allow' end) as verdict
from q left join f using (page_id)""",
    "op5_decontaminate": r"""
with t as (select doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') as w from documents),
b as (select distinct cast(item_id as varchar) as item, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') as w from benchmark where item_id is not null),
g as (select distinct item, least(10, len(w)) as n, array_to_string(w[i : i + least(10, len(w)) - 1], ' ') as gram from (select item, w, unnest(range(1, greatest(1, len(w) - 9) + 1)) as i from b where len(w) > 0)),
sizes as (select distinct n from g),
x as (select doc_id, n, i, array_to_string(w[i : i + n - 1], ' ') as gram from (select doc_id, w, n, unnest(range(1, len(w) - n + 2)) as i from t, sizes)),
h as (select x.doc_id, x.i, x.n, g.item from x join g on x.n = g.n and x.gram = g.gram),
c as (select doc_id, count(distinct p) as n_hit from (select doc_id, unnest(range(i, i + n)) as p from h) group by doc_id),
m as (select doc_id, count(*) as n_items, string_agg(item, ',' order by item) as items from (select distinct doc_id, item from h) group by doc_id)
select t.doc_id, len(w)::bigint as n_words, coalesce(n_hit, 0)::bigint as n_hit, coalesce(n_items, 0)::bigint as n_items, sha256(coalesce(items, '')) as items_sha256, coalesce(n_hit, 0) > 0 as contaminated
from t left join c using (doc_id) left join m using (doc_id)""",
    "op9_preference_format": r"""
with c as (select conv_id as conv, list({'role': coalesce(role, 'unknown'), 'text': coalesce(text, '')} order by turn nulls first, coalesce(role, 'unknown'), coalesce(text, '')) as t from (select distinct conv_id, turn, role, text from conversations where conv_id is not null) group by conv_id),
d as (select conv, t, list_filter(t, lambda x: x.role = 'assistant')[-1] as reply, len(t) - list_position(list_reverse(list_transform(t, lambda x: x.role)), 'assistant') as head from c),
e as (select a.conv as pair_id, a.t as c, case when a.reply is null then a.t when b.reply is null then a.t[1:a.head] else list_append(a.t[1:a.head], b.reply) end as r from d a left join d b on b.conv = xor(a.conv, 1)),
f as (select pair_id, c, r, coalesce(list_position(list_transform(range(1, least(len(c), len(r)) + 1), lambda i: c[i] = r[i]), false) - 1, least(len(c), len(r))) as n from e),
g as (select pair_id, n, c[1:n] as p, c[n + 1:] as c, r[n + 1:] as r from f)
select pair_id, n::int as n_prefix,
  coalesce(array_to_string(list_transform(p, lambda x: '<|' || x.role || '|>' || chr(10) || x.text || chr(10) || '<|end|>' || chr(10)), ''), '') as prompt,
  coalesce(array_to_string(list_transform(c, lambda x: '<|' || x.role || '|>' || chr(10) || x.text || chr(10) || '<|end|>' || chr(10)), ''), '') as chosen,
  coalesce(array_to_string(list_transform(r, lambda x: '<|' || x.role || '|>' || chr(10) || x.text || chr(10) || '<|end|>' || chr(10)), ''), '') as rejected,
  coalesce(array_to_string(list_transform(list_filter(range(1, len(c) + 1), lambda i: c[i].role = 'assistant'), lambda i: concat(coalesce(list_sum(list_transform(c[1:i - 1], lambda x: length(x.role) + length(x.text) + 14)), 0)::bigint + length(c[i].role) + 5, '-', list_sum(list_transform(c[1:i], lambda x: length(x.role) + length(x.text) + 14))::bigint)), ','), '') as chosen_mask,
  coalesce(array_to_string(list_transform(list_filter(range(1, len(r) + 1), lambda i: r[i].role = 'assistant'), lambda i: concat(coalesce(list_sum(list_transform(r[1:i - 1], lambda x: length(x.role) + length(x.text) + 14)), 0)::bigint + length(r[i].role) + 5, '-', list_sum(list_transform(r[1:i], lambda x: length(x.role) + length(x.text) + 14))::bigint)), ','), '') as rejected_mask
from g""",
}
