"""Secret scans with corpus-wide ownership frequency. DataFrame functions only.

Candidates: assigned values, access keys and long hexadecimal runs (the base kinds), and provider formats (`format`). Each candidate's
value is hashed, and the hashes are counted over the whole corpus by distinct repositories and owners, first without
repeats of one owner, so a value copied a billion times is one row per task and owner. A value of several owners, or of more
than `most_repos` repositories of one, is a widely copied example; a value that one owner keeps in few places looks live. The
method adds the spans of live `format` candidates; base spans always stay.

Matches of a pattern are taken leftmost and apart: the pieces between matches (split) and the matches themselves give
their places. Places are code points, ends exclusive. Running sums over a text's matches are taken by blocks, and a masked text
is put together from blocks of code points, so the work grows with the matches and the text, not with their product.

Nulls: a null text is empty. Null repositories and owners count as one of their own. Repeated rows get the same spans.
Empty tables give no rows.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import materialize

#: Pattern, group that holds the value, least length of that group; in the order of the kinds.
KINDS = {
    "assign": (r"""(?i:(password|passwd|secret|token|api_?key))["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", 2, 8),
    "access": (r"AKIA[A-Z0-9]+", 0, 16),
    "hex": (r"[0-9a-f]{32,}", 0, 32),
    "format": (
        r"(?:gh[pousr]_[A-Za-z0-9]{36,}|xox[abprs]-[A-Za-z0-9-]{10,}|sk_live_[A-Za-z0-9]{16,}|AIza[A-Za-z0-9_-]{35}"
        r"|eyJ[A-Za-z0-9_-]{10,}\.[A-Za-z0-9_-]{10,}\.[A-Za-z0-9_-]{10,}|-----BEGIN [A-Z ]{0,20}PRIVATE KEY-----|[0-9A-F]{32,})",
        0,
        16,
    ),
}
BASE = ("assign", "access", "hex")
SPAN = "struct<s:int,k:int,e:int,h:bigint>"
#: A live value's repositories at most.
MOST_REPOS = 3
#: Matches in a block of running sums; code points in a block of a text that is masked.
SUM_BLOCK, TEXT_BLOCK = 256, 4096


def let(value: Column, body) -> Column:
    """body(value), the value computed once."""
    return F.element_at(F.transform(F.array(value), body), 1)


def running(x: Column, combine, zero: Column) -> Column:
    """combine() of the numbers before each one of the array, block by block."""
    blocks = lambda x: F.sequence(F.lit(0), F.greatest(F.ceil(F.size(x) / SUM_BLOCK).cast("int") - 1, F.lit(0)))
    whole = lambda x: F.transform(blocks(x), lambda b: F.aggregate(F.slice(x, b * SUM_BLOCK + 1, F.lit(SUM_BLOCK)), zero, combine))
    before = lambda t: F.transform(t, lambda _, b: F.aggregate(F.slice(t, F.lit(1), b), zero, combine))

    def each(x: Column, base: Column) -> Column:
        def one(_, i):
            b = F.floor(i / SUM_BLOCK).cast("int")
            return F.aggregate(F.slice(x, b * SUM_BLOCK + 1, i - b * SUM_BLOCK), F.get(base, b), combine)

        return F.transform(x, one)

    return let(x, lambda x: let(let(whole(x), before), lambda base: each(x, base)))


def matches(text: Column, kind: str) -> Column:
    """array<struct<s,k,e,h>> of one kind: start, number of the kind, end, hash of the value."""
    pattern, group, least = KINDS[kind]
    k = list(KINDS).index(kind)
    whole = F.regexp_extract_all(text, F.lit(pattern), F.lit(0))
    value = F.regexp_extract_all(text, F.lit(pattern), F.lit(group)) if group else whole
    # of texts with a match only, so there is one gap more than matches
    zipped = F.arrays_zip(F.transform(F.split(text, pattern, -1), F.length).alias("gap"), F.transform(whole, F.length).alias("n"), value.alias("value"))

    def placed(z: Column) -> Column:
        steps = F.transform(z, lambda x: x["gap"] + F.coalesce(x["n"], F.lit(0)))
        spans = lambda at: F.transform(
            z, lambda x, i: F.struct((F.get(at, i) + x["gap"]).alias("s"), F.lit(k).alias("k"), (F.get(at, i) + x["gap"] + x["n"]).alias("e"), F.when(F.length(x["value"]) >= least, F.xxhash64(x["value"])).alias("h"))
        )
        return let(running(steps, lambda a, b: a + b, F.lit(0)), spans)

    found = F.filter(let(zipped, placed), lambda x: x["h"].isNotNull())
    return F.when(text.rlike(pattern), found.cast(f"array<{SPAN}>")).otherwise(F.expr(f"cast(array() as array<{SPAN}>)"))


def candidates(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", repo: Column | None = None, owner: Column | None = None) -> DataFrame:
    """doc_id, tag (hash of the text, so rows alike in both are alike), repo, owner, base spans in order, other spans. Row-local."""
    own = docs.select(
        F.col(id_col).alias("doc_id"), F.coalesce(F.col(text_col), F.lit("")).alias("text"), (repo if repo is not None else F.lit(None).cast("string")).alias("repo"),
        (owner if owner is not None else F.lit(None).cast("string")).alias("owner"),
    )
    base = F.array_sort(F.concat(*[matches(F.col("text"), k) for k in BASE]))
    return own.select("doc_id", F.xxhash64("text").alias("tag"), "repo", "owner", base.alias("base"), matches(F.col("text"), "format").alias("other"))


def ownership(found: DataFrame, most_repos: int = MOST_REPOS) -> DataFrame:
    """h, n_repos, n_owners, live of every candidate value."""
    flat = found.select(F.explode(F.concat("base", "other")).alias("x"), "repo", "owner").select(F.col("x.h").alias("h"), F.coalesce("repo", F.lit("\0")).alias("repo"), F.coalesce("owner", F.lit("\0")).alias("owner"))
    counted = flat.groupBy("h", "owner", "repo").agg(F.lit(1)).groupBy("h", "owner").agg(F.count("*").alias("repos"))
    # a repository belongs to the owner that is named beside it
    known = counted.groupBy("h").agg(F.count("*").alias("n_owners"), F.sum("repos").alias("n_repos"))
    return known.withColumn("live", (F.col("n_owners") == 1) & (F.col("n_repos") <= most_repos))


def shown(spans: Column) -> Column:
    """kind:start:end, comma-joined, in the order of start and kind."""
    names = F.array(*[F.lit(k) for k in KINDS])
    return F.array_join(F.transform(F.array_sort(spans), lambda x: F.concat_ws(":", F.element_at(names, x["k"] + 1), x["s"].cast("string"), x["e"].cast("string"))), ",")


def scan(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", repo: Column | None = None, owner: Column | None = None, most_repos: int = MOST_REPOS) -> DataFrame:
    """doc_id, tag, base, spans (base and added), n_live and n_example (candidates by ownership) of every row."""
    found = materialize(candidates(docs, id_col, text_col, repo, owner), "candidates")
    return judged(found, most_repos)


def judged(found: DataFrame, most_repos: int = MOST_REPOS) -> DataFrame:
    with_some = found.filter((F.size("base") > 0) | (F.size("other") > 0))
    flat = with_some.select("doc_id", "tag", F.explode(F.concat("base", "other")).alias("x")).distinct()
    known = flat.join(ownership(with_some, most_repos), flat["x.h"] == F.col("h")).select("doc_id", "tag", "x", "live")
    added = F.collect_list(F.when(F.col("live") & (F.col("x.k") >= len(BASE)), F.col("x")))
    each = known.groupBy("doc_id", "tag").agg(added.alias("added"), F.count(F.when(F.col("live"), 1)).alias("n_live"), F.count(F.when(~F.col("live"), 1)).alias("n_example"))
    each = each.select(F.col("doc_id").alias("a_id"), F.col("tag").alias("a_tag"), "added", "n_live", "n_example")
    out = found.join(each, F.col("doc_id").eqNullSafe(F.col("a_id")) & (F.col("tag") == F.col("a_tag")), "left")
    none = F.expr(f"cast(array() as array<{SPAN}>)")
    return out.select("doc_id", "tag", "base", F.concat("base", F.coalesce("added", none)).alias("spans"), F.coalesce("n_live", F.lit(0)).alias("n_live"), F.coalesce("n_example", F.lit(0)).alias("n_example"))


def redact(docs: DataFrame, mask: str = "[SECRET]", id_col: str = "doc_id", text_col: str = "text", repo: Column | None = None, owner: Column | None = None) -> DataFrame:
    """The documents' own columns, each found span (overlaps joined) replaced by the mask; a null text stays null."""
    columns = docs.columns
    found = scan(docs, id_col, text_col, repo, owner).filter(F.size("spans") > 0).select(F.col("doc_id").alias("f_id"), F.col("tag").alias("f_tag"), "spans").dropDuplicates(["f_id", "f_tag"])
    inner = docs.select(F.struct(*[F.col(c) for c in columns]).alias("row"), F.col(id_col).alias("doc_id"), F.xxhash64(F.coalesce(F.col(text_col), F.lit(""))).alias("tag"), F.col(text_col).alias("text"))
    joined = inner.join(found, F.col("doc_id").eqNullSafe(F.col("f_id")) & (F.col("tag") == F.col("f_tag")), "left")
    size = TEXT_BLOCK

    def piece(blocks: Column, a: Column, b: Column) -> Column:
        """Code points a to b of the text."""
        i, j = F.floor(a / size).cast("int"), F.floor(b / size).cast("int")
        first, last = F.coalesce(F.get(blocks, i), F.lit("")), F.coalesce(F.get(blocks, j), F.lit(""))
        within = F.substring(first, a - i * size + 1, b - a)
        across = F.concat(F.substring(first, a - i * size + 1, F.lit(size)), F.array_join(F.slice(blocks, i + 2, F.greatest(j - i - 1, F.lit(0))), ""), F.substring(last, F.lit(1), b - j * size))
        return F.when(b <= a, F.lit("")).when(i == j, within).otherwise(across)

    def cleaned(spans: Column, blocks: Column, to: Column) -> Column:
        # a span that starts where others have ended is masked, with the gap before it; others lie in a mask
        masked = F.transform(spans, lambda x, i: F.when(x["s"] >= F.get(to, i), F.concat(piece(blocks, F.get(to, i), x["s"]), F.lit(mask))).otherwise(F.lit("")))
        return F.concat(F.array_join(masked, ""), piece(blocks, F.array_max(F.transform(spans, lambda x: x["e"])), F.length("text")))

    blocks = F.regexp_extract_all(F.col("text"), F.lit(f"(?s).{{1,{size}}}"), F.lit(0))
    ends = lambda x: running(F.transform(x, lambda y: y["e"]), lambda a, b: F.greatest(a, b), F.lit(0))
    clean = let(F.array_sort("spans"), lambda x: let(blocks, lambda b: let(ends(x), lambda to: cleaned(x, b, to))))
    text = F.when(F.col("spans").isNotNull() & F.col("text").isNotNull(), clean).otherwise(F.col("text"))
    return joined.select(*[(text if c == text_col else F.col(f"row.`{c}`")).alias(c) for c in columns])
