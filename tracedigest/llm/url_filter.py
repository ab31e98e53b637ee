"""URL filters: pattern rules indexed by their rarest literal token.

A rule is a regular expression with an action, and the literal tokens that every matching url must hold. Corpus-wide
token counts pick each rule's rarest token; a url's tokens fetch its candidate rules from that index, and only those
run their regular expression. Rules without a usable literal token are always candidates.

Up to CLOSURE_BYTES of rules travel in the kernel's closure, one row-local pass over the urls. More rules stay a table: different
urls meet them by an equi-join on the token, so there is no bound on their number. The counts are a row per literal token.

A null url, or one without "://", has an empty host and path and fits no host rule. Empty table: no rows. Repeated rows get
the same verdict; a url may have any length. A rule without a token in the table form meets every different url.
"""

from __future__ import annotations

import re
from collections.abc import Iterator
from dataclasses import dataclass

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import materialize

#: Bytes of patterns, names and tokens that travel in a closure.
CLOSURE_BYTES = 4 << 20
TOKEN = re.compile(r"[A-Za-z0-9]+")
RULE_COLUMNS = "name string, action string, pattern string, tokens array<string>, weight int, named boolean"


@dataclass(frozen=True)
class Rule:
    """name and action are reported; weight ranks the rules that fit (the longest host rule wins); tokens are literals
    that stand delimited in every url that fits."""

    name: str
    action: str
    pattern: str
    tokens: tuple[str, ...]
    weight: int
    named: bool = True


def host_rule(action: str, rule: str) -> Rule:
    """`host/path`: fits the host and its subdomains if the path starts with the rule's."""
    host, slash, path = rule.partition("/")
    path = slash + path
    whole = path[: path.rfind("/") + 1]  # a token that the next character may lengthen is no literal
    tokens = TOKEN.findall(host) + TOKEN.findall(whole)
    return Rule(rule, action, rf"(?:[^\x00]*\.)?{re.escape(host)}\x00{re.escape(path)}", tuple(tokens), 1_000 + len(rule))


def host_word_rule(word: str, action: str = "block") -> Rule:
    """Fits hosts with `word` between dots, dashes or the host's ends."""
    return Rule(word, action, rf"(?:[^\x00]*[.-])?{re.escape(word)}(?:[.-][^\x00]*)?\x00", tuple(TOKEN.findall(word)), len(word), named=False)


def path_word_rule(word: str, action: str = "block") -> Rule:
    """Fits paths with `word` between any of / . _ - or the path's end."""
    return Rule("/" + word, action, rf"[^\x00]*\x00(?:.*[/._-])?{re.escape(word)}(?:[/._-].*)?$", tuple(TOKEN.findall(word)), len(word), named=False)


#: The rules that the query is asked to judge by.
GIVEN_RULES = (("allow", "com/"), ("block", "example.com/en/"), ("allow", "www.example.com/en/"), ("block", "net/es/"), ("block", "net/fr/"))
#: The method's own patterns, for urls that no given rule fits: words of hosts, and of paths.
HOST_WORDS = (
    "ads-track", "adserver", "betting", "bets", "bingo", "casino", "cheap-pills", "click-bait", "crack-keys", "dating-now", "doubleclick", "escorts", "free-money", "jackpot", "keygen",
    "link-farm", "lottery", "payday-loan", "pharmacy-online", "phishing", "poker", "porn", "replica-watches", "slots", "spam-farm", "sportsbook", "torrents", "viagra", "warez", "win-prize", "xxx",
)
PATH_WORDS = ("casino", "escorts", "payday-loan", "poker", "porn", "viagra", "warez", "xxx")


def default_rules() -> list[Rule]:
    return [host_rule(*x) for x in GIVEN_RULES] + [host_word_rule(x) for x in HOST_WORDS] + [path_word_rule(x) for x in PATH_WORDS]


def rule_table(spark: SparkSession, rules: list[Rule]) -> DataFrame:
    """Rules as rows; a table of rules may as well come from a file."""
    return spark.createDataFrame([(r.name, r.action, r.pattern, list(r.tokens), r.weight, r.named) for r in rules], RULE_COLUMNS)


def with_parts(pages: DataFrame, url_col: str = "url") -> DataFrame:
    """page rows plus host and path, by built-in functions."""
    rest = F.when(F.locate("://", F.col(url_col)) > 0, F.expr(f"substring(`{url_col}`, locate('://', `{url_col}`) + 3)")).otherwise(F.lit(""))
    host = F.regexp_extract(rest, r"(?s)^([^/?#]*)", 1)
    host = F.translate(host, "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")
    path = F.regexp_extract(rest, r"(?s)^[^/?#]*([^?#]*)", 1)
    return pages.withColumn("host", F.coalesce(host, F.lit(""))).withColumn("path", F.coalesce(path, F.lit("")))


def tokens_of(rows: DataFrame) -> DataFrame:
    """host, path, token: a row per different token."""
    return rows.select("host", "path", F.explode(F.array_distinct(F.regexp_extract_all(F.concat_ws("/", "host", "path"), F.lit(TOKEN.pattern), 0))).alias("token"))


def token_counts(urls: DataFrame, wanted: DataFrame) -> DataFrame:
    """token, n: how many rows hold each wanted token, over the whole table."""
    return tokens_of(urls).join(wanted.select("token").distinct(), "token", "left_semi").groupBy("token").agg(F.count("*").alias("n"))


def index(rules: list[Rule], counts: dict[str, int]) -> tuple[dict[str, list[int]], list[int]]:
    """Rule numbers by rarest literal token, and those without one."""
    by_token: dict[str, list[int]] = {}
    always = []
    for i, rule in enumerate(rules):
        if rule.tokens:
            by_token.setdefault(min(rule.tokens, key=lambda t: (counts.get(t, 0), t)), []).append(i)
        else:
            always.append(i)
    return by_token, always


def judge(pages: DataFrame, rules: list[Rule] | DataFrame | None = None, id_col: str = "page_id", url_col: str = "url", default: str = "allow", closure_bytes: int = CLOSURE_BYTES) -> DataFrame:
    """page_id, host, path, rule (of the named rule that decided, else null), verdict, matched (the deciding rule's name,
    named or not), tried (regular expressions run)."""
    spark = pages.sparkSession
    urls = with_parts(pages.select(F.col(id_col).alias("page_id"), F.col(url_col).alias("url"))).select("page_id", "host", "path")
    table = rules if isinstance(rules, DataFrame) else rule_table(spark, default_rules() if rules is None else rules)
    size = table.agg(F.sum(F.octet_length("name") + F.octet_length("pattern") + F.octet_length(F.array_join("tokens", "  ")) + 100)).first()[0] or 0
    if size > closure_bytes:
        return judged_by_join(urls, table, default)
    own = [Rule(r["name"], r["action"], r["pattern"], tuple(r["tokens"]), r["weight"], r["named"]) for r in table.collect()]
    wanted = table.select(F.explode("tokens").alias("token"))
    counts = {r["token"]: r["n"] for r in token_counts(urls, F.broadcast(wanted)).collect()}  # at most the rules' tokens
    return judged_in_pass(urls, own, *index(own, counts), default)


def judged_in_pass(urls: DataFrame, rules: list[Rule], by_token: dict[str, list[int]], always: list[int], default: str) -> DataFrame:
    kind = urls.schema["page_id"].dataType.simpleString()

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        compiled: dict[int, re.Pattern] = {}
        for batch in batches:
            names, verdicts, matched, tried = [], [], [], []
            for host, path in zip(batch.column("host").to_pylist(), batch.column("path").to_pylist(), strict=True):
                candidates = list(always)
                for token in set(TOKEN.findall(f"{host}/{path}")):
                    candidates += by_token.get(token, ())
                best, subject = None, f"{host}\0{path}"
                for i in candidates:
                    if i not in compiled:
                        compiled[i] = re.compile(rules[i].pattern, re.S)
                    if compiled[i].match(subject) and (best is None or (-rules[i].weight, rules[i].name) < (-best.weight, best.name)):
                        best = rules[i]
                names.append(best.name if best and best.named else None)
                matched.append(best.name if best else None)
                verdicts.append(best.action if best else default)
                tried.append(len(candidates))
            yield pa.RecordBatch.from_arrays(
                [batch.column("page_id"), batch.column("host"), batch.column("path"), pa.array(names, pa.string()), pa.array(verdicts, pa.string()), pa.array(matched, pa.string()), pa.array(tried, pa.int32())],
                ["page_id", "host", "path", "rule", "verdict", "matched", "tried"],
            )

    return urls.mapInArrow(kernel, f"page_id {kind}, host string, path string, rule string, verdict string, matched string, tried int")


def judged_by_join(urls: DataFrame, table: DataFrame, default: str) -> DataFrame:
    """The same for any number of rules: rules by rarest token, different urls by token, one equi-join. A rule's place in the pattern
    language is that of Java here, which has what these rules use."""
    numbered = materialize(table.select("*", F.monotonically_increasing_id().alias("no")), "url-rules")
    different = urls.select("host", "path").distinct()
    wanted = numbered.select("no", F.explode("tokens").alias("token"))
    counts = token_counts(urls, wanted)
    rarest = wanted.join(counts, "token", "left").groupBy("no").agg(F.min_by("token", F.struct(F.coalesce("n", F.lit(0)), "token")).alias("token"))
    indexed = numbered.join(rarest, "no", "left")
    by_token = tokens_of(different).join(indexed.filter("token is not null"), "token")
    always = indexed.filter("token is null").drop("token")
    pairs = by_token.select("host", "path", "name", "action", "pattern", "weight", "named").unionByName(different.join(F.broadcast(always), how="cross").select("host", "path", "name", "action", "pattern", "weight", "named"))
    fits = F.expr("rlike(concat(host, '\\u0000', path), concat('(?s)^(?:', pattern, ')'))")
    best = F.max_by(F.struct("name", "action", "named"), F.when(fits, F.struct(F.col("weight"), F.concat(F.transform(F.split("name", ""), lambda c: -F.ascii(c)), F.array(F.lit(1))))))
    found = pairs.groupBy("host", "path").agg(best.alias("best"), F.count("*").cast("int").alias("tried"))
    out = urls.join(found, ["host", "path"], "left")
    return out.select(
        "page_id", "host", "path", F.when(F.col("best.named"), F.col("best.name")).alias("rule"), F.coalesce("best.action", F.lit(default)).alias("verdict"), F.col("best.name").alias("matched"),
        F.coalesce("tried", F.lit(0)).alias("tried"),
    )
