"""DuckDB SQL that restarts from the tables: traces, blocks, filters and verdicts as common table expressions.

Bytes are hexadecimal text (two digits a byte); searching is done on digits spaced by byte, so that no match starts on half a byte.
"""

from __future__ import annotations

from ..functions.hashing import POS, PRIME, STEP_A, STEP_B, STEP_C, STEP_D, STEP_I

DOCS = "trace(flow_key, seq, hx, src, dst) as (select doc_id::varchar, 0::bigint, hex(encode(coalesce(text, ''))), source, lang from documents)"
DOCS_SOURCE = "trace(flow_key, seq, hx, src, dst) as (select concat_ws('|', source, lang), doc_id, hex(encode(coalesce(text, ''))), source, lang from documents)"
DOCS_SKEW = "trace(flow_key, seq, hx, src, dst) as (select case when doc_id % 16 = 0 then doc_id::varchar else concat_ws('|', source, lang) end, doc_id, hex(encode(coalesce(text, ''))), source, lang from documents)"
PAGES = "trace(flow_key, seq, hx) as (select page_id::varchar, 0::bigint, hex(encode(coalesce(html, ''))) from pages)"
CONVS = "trace(flow_key, seq, hx, proto) as (select conv_id::varchar, turn, hex(encode(coalesce(text, ''))), role from conversations)"
LEDGER_ROWS = """rows_(s, c, ok, ln, y, rf, txt) as (select s_nationkey, c_nationkey, l_orderkey, l_linenumber, year(l_shipdate), l_returnflag,
  concat_ws('|', l_orderkey, l_partkey, l_suppkey, l_linenumber, round(l_quantity * 100)::bigint, round(l_extendedprice * 100)::bigint, round(l_discount * 100)::bigint, round(l_tax * 100)::bigint, l_returnflag, l_linestatus, datediff('day', date '1970-01-01', l_shipdate::date))
  from lineitem join orders on l_orderkey = o_orderkey join supplier on l_suppkey = s_suppkey join customer on o_custkey = c_custkey)"""


def hash_sql(value: str, instance: int = 0) -> str:
    x = f"((({value}) % {PRIME}) * {STEP_A} + {STEP_B + STEP_I * instance}) % {PRIME}"
    return f"((({x}) * ({x}) + ({x})) % {PRIME} * {STEP_C} + {STEP_D}) % {PRIME}"


def number(hx: str, at: str, digits: int) -> str:
    return f"('0x' || substr({hx}, {at}, {digits}))::bigint"


def bounds(src: str = "trace", out: str = "bounds", window: int = 64, width: int = 5, instance: int = 0) -> str:
    """out(flow_key, seq, pos)."""
    byte = lambda a, b: "('0x' || " + " || ".join("b" if i == 0 else f"lead(b, {i}) over w" for i in range(a, b)) + ")::bigint"
    # wide hashes in two halves; 256^5 mod the prime is 512
    value = byte(0, width) if width <= 7 else f"({byte(0, width - 5)}) % {PRIME} * 512 + {byte(width - 5, width)}"
    return f"""{out}_l as (select flow_key, seq, generate_subscripts(l, 1) - 1 as pos, len(l) - {width - 1} as n, unnest(l) as b from (select flow_key, seq, regexp_extract_all(hx, '..') as l from {src} where len(hx) // 2 >= {window + width - 1})),
{out}_v as (select flow_key, seq, pos, n, v from (select flow_key, seq, pos, n, case when pos < n then {value} end as v from {out}_l window w as (partition by flow_key, seq order by pos)) where pos < n),
{out}_x as (select flow_key, seq, pos, n, (v % {PRIME} * {STEP_A} + {STEP_B + STEP_I * instance}) % {PRIME} as x from {out}_v),
{out}_h as (select flow_key, seq, pos, n, ((x * x + x) % {PRIME} * {STEP_C} + {STEP_D}) % {PRIME} * {POS} + ({POS - 1} - pos) as h from {out}_x),
{out}_w as (select flow_key, seq, pos, n, min(h) over (partition by flow_key, seq order by pos rows between current row and {window - 1} following) as least from {out}_h),
{out} as (select distinct flow_key, seq, ({POS - 1} - least % {POS})::int as pos from {out}_w where pos <= n - {window})"""


def blocks(src: str = "trace", out: str = "blk", window: int = 64, width: int = 5, instance: int = 0) -> str:
    """out(flow_key, seq, block_no, start, size, block)."""
    b = f"{out}_b"
    return f"""{bounds(src, b, window, width, instance)},
{out}_n as (select flow_key, seq, pos, lead(pos) over (partition by flow_key, seq order by pos) as nxt, (row_number() over (partition by flow_key, seq order by pos) - 1)::int as block_no from {b}),
{out} as (select m.flow_key, m.seq, block_no, pos as start, (nxt - pos + {width})::int as size, unhex(substr(hx, 2 * pos + 1, 2 * (nxt - pos + {width}))) as block
  from {out}_n m join {src} t on m.flow_key = t.flow_key and m.seq = t.seq where nxt is not null)"""


def fixed(src: str = "trace", out: str = "blk", size: int = 32) -> str:
    return f"""{out} as (select flow_key, seq, i::int as block_no, (i * {size})::int as start, {size}::int as size, unhex(substr(hx, 2 * i * {size} + 1, {2 * size})) as block
  from (select flow_key, seq, hx, unnest(range(0, len(hx) // 2 // {size})) as i from {src}))"""


SPACED = "regexp_replace({}, '(..)', '\\1 ', 'g')"

SLICES = """slices as (select doc_id as excerpt_id, substr(hx, 2 * (50 + (doc_id * 7919) % (n - 300)) + 1, 400) as hx
  from (select doc_id, hex(encode(coalesce(text, ''))) as hx, len(hex(encode(coalesce(text, '')))) // 2 as n from documents) where n >= 400)"""

UNIQUE = f"""{SLICES},
spaced as (select flow_key, {SPACED.format('hx')} as sp from trace),
found as (select excerpt_id, count(distinct flow_key) as n, min(flow_key) as true_flow from (select excerpt_id, {SPACED.format('hx')} as xp from slices) x join spaced on contains(sp, xp) group by excerpt_id),
excerpts as (select excerpt_id, hx, true_flow from slices join found using (excerpt_id) where n = 1 order by excerpt_id limit 1000),
xt as (select excerpt_id::varchar as flow_key, 0::bigint as seq, hx from excerpts)"""


#: The same without the experiments' number of excerpts.
UNIQUE_ALL = UNIQUE.replace(" order by excerpt_id limit 1000", "")


#: Filter size in bits at 100:1, of the trace.
SIZE = "size_ as (select greatest(32, 8 * sum(len(hx) // 2) // 100)::bigint as m, sum(len(hx) // 2)::bigint as raw, count(distinct flow_key) as flows from trace)"


def digest(block: str, flow: str | None = None) -> str:
    return f"md5({block} || encode('|' || {flow}))" if flow else f"md5({block})"


def bits(elements: str, out: str = "bits", per: str = "cfg") -> str:
    """out(config_id, section, pos) of elements(config_id, d, tag) under cfg(config_id, j, k, ms): the bits that are set."""
    return f"""{out} as (select distinct config_id, section, pos from (select e.config_id, case when tag is null then {number('d', '1', 8)} % j else tag end as section,
  ({number('d', '9', 12)} + r * {number('d', '21', 12)}) % ms as pos from {elements} e join {per} using (config_id), range(8) g(r) where r < k))"""


def evaluation(entries: list[dict], blk: str = "blk", xblk: str = "xblk") -> str:
    """missed(config_id, excerpt_id, flow_key): pairs that a configuration rules out. Needs trace, size_, blk, xblk."""
    rows = ", ".join(f"({i}, {e.get('threshold', 0)}, {e.get('sections', 1)}, {e.get('k', 1)}, {str(bool(e.get('index'))).lower()}, {1 if e.get('feature') == 'hash' else e.get('sections', 1)})" for i, e in enumerate(entries))
    return f"""cfg as (select config_id, t, ji, j, k, idx, m // j as ms from (values {rows}) c(config_id, t, ji, k, idx, j), (select m from size_)),
el as (select config_id, {digest('block')} as d, null::bigint as tag from {blk}, cfg where size >= t union all select config_id, {digest('block', 'flow_key')}, null from {blk}, cfg where size >= t),
{bits('el')},
xd as (select flow_key::bigint as excerpt_id, block_no, size, block, {digest('block')} as d from {xblk}),
flows as (select distinct flow_key from trace),
ask1 as (select config_id, excerpt_id, {number('d', '1', 8)} % j as section, ({number('d', '9', 12)} + r * {number('d', '21', 12)}) % ms as pos from xd, cfg, range(8) g(r) where size >= t and r < k),
gone as (select distinct config_id, excerpt_id from ask1 anti join bits using (config_id, section, pos)),
fd as (select excerpt_id, flow_key, size, {digest('block', 'flow_key')} as d from xd, flows),
fp as (select excerpt_id, flow_key, size, {number('d', '1', 8)} as sel, {number('d', '9', 12)} as g1, {number('d', '21', 12)} as g2 from fd),
ask2 as (select config_id, excerpt_id, flow_key, sel % j as section, (g1 + r * g2) % ms as pos from fp, cfg, range(8) g(r) where size >= t and r < k),
miss2 as (select distinct config_id, excerpt_id, flow_key from ask2 anti join bits using (config_id, section, pos)),
touched as (select distinct config_id, flow_key, {number(digest('block'), '1', 8)} % ji as section from {blk}, cfg where size >= t and idx),
need as (select distinct config_id, excerpt_id, {number('d', '1', 8)} % ji as section from xd, cfg where size >= t and idx),
miss3 as (select distinct config_id, excerpt_id, flow_key from (select config_id, excerpt_id, section, flow_key from need, flows) n anti join touched using (config_id, flow_key, section)),
missed as (select config_id, excerpt_id, flow_key from miss2 union select config_id, excerpt_id, flow_key from miss3 union select config_id, excerpt_id, flow_key from gone, flows),
rate as (select config_id, (select count(*) from excerpts) as excerpts, (select count(*) from excerpts) * (select flows from size_) - count(excerpt_id) as reported from cfg left join missed using (config_id) group by config_id)"""


RATE = "excerpts, reported::bigint as reported, (reported - excerpts)::bigint as false_flows, round((reported - excerpts) / (excerpts * (select flows from size_)), 6) as fpr"
def setup(packets: str = DOCS) -> str:
    return f"with {packets}, {SIZE}, {blocks()}, {UNIQUE}, {blocks('xt', 'xblk')}"


SETUP = setup()
SETUP_ALL = SETUP.replace(UNIQUE, UNIQUE_ALL)


def sweep(entries: list[dict], columns: str, packets: str = DOCS) -> str:
    return f"{setup(packets)}, {evaluation(entries)} select {columns}, {RATE} from rate join cfg using (config_id)"


def words(keys: str = "") -> str:
    return f"select {keys}section::int as section, (pos // 32)::int as word_ix, bit_or(1::bigint << (pos % 32)::int)::bigint as word from bits group by all"


def filter_words(sections: int, k: int, flow_blocks: bool = True, src: str = DOCS) -> str:
    both = f" union all select 0, {digest('block', 'flow_key')}, null from blk" if flow_blocks else ""
    return f"""with {src}, {SIZE}, {blocks()}, cfg as (select 0 as config_id, {sections} as j, {k} as k, greatest({32 * sections}, m) // {sections} as ms from size_),
el as (select 0 as config_id, {digest('block')} as d, null::bigint as tag from blk{both}), {bits('el')} """


def entropy(symbol: int, sections: int) -> str:
    """Symbols of the index at threshold 0: bitmaps as hexadecimal text, least bit first in each byte."""
    return f"""with {DOCS}, {blocks()}, touched as (select distinct flow_key, {number(digest('block'), '1', 8)} % {sections} as s from blk),
bytes as (select f.flow_key, b, coalesce(bit_or((1 << (s % 8)::int)), 0) as v from (select distinct flow_key from trace) f cross join range({sections // 8}) g(b) left join touched t on t.flow_key = f.flow_key and t.s // 8 = b group by f.flow_key, b),
sym as (select flow_key, b // {symbol} as i, string_agg(printf('%02X', v), '' order by b) as symbol from bytes group by flow_key, b // {symbol}),
n as (select symbol, count(*) as n from sym group by symbol),
e as (select sum(n)::bigint as symbols, count(*) as different, sum(-(n / total) * log2(n / total)) as h from n, (select sum(n) as total from n))
select {symbol} as symbol_bytes, symbols, different, round(h, 6) as entropy, round(symbols * h / 8 + different * {symbol}, 3) as bound, round(symbols * {symbol} / (symbols * h / 8 + different * {symbol}), 6) as best_ratio from e"""
