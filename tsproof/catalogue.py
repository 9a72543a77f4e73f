"""Every registered query of the engine and, where SQL can express it, its SQL."""

from __future__ import annotations

from collections.abc import Callable
from functools import reduce

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from tsproof import experiments as ex
from tsproof import streaming, udf
from tsproof.functions import cover, encoding, lines
from tsproof.operators import aggtree, approx, attacks, baselines, budget, client, costs, exact, relops, segments, sliding
from tsproof.plans import ordering, planner, streams, workload
from tsproof.sources import read_table, round_trip, scratch, written

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
SQL: dict[str, str] = {}


def query(name: str, sql: str | None = None) -> Callable[[Query], Query]:
    def add(f: Query) -> Query:
        QUERIES[name] = f
        if sql:
            SQL[name] = sql
        return f

    return add


# ---- streams as SQL -------------------------------------------------------------------------------------------------
_TAGS = "'event_type=' || event_type || ',k=' || coalesce(json_extract_string(props, '$.k'), '~') || ',user_id=' || user_id"


def _event_sql(sid: str = "'all'", v: str = "round(value * 100)::bigint") -> str:
    return f"select ({sid})::varchar as sid, row_number() over (partition by {sid} order by ts, event_id) - 1 as pos, epoch_us(ts) as t, event_id // 10 as height, (event_id % 10)::int as i, {v} as v, {_TAGS} as tags, event_type, user_id from events"


_ORDER = "select 'orders' as sid, row_number() over (order by o_orderdate, o_orderkey) - 1 as pos, epoch_us(o_orderdate) as t, epoch_us(o_orderdate) // 86400000000 as height, (row_number() over (partition by o_orderdate order by o_orderkey) - 1)::int as i, round(o_totalprice * 100)::bigint as v, 'status=' || o_orderstatus as tags from orders"
_LINE_KEYS = ", ".join(sorted("l_orderkey l_partkey l_suppkey l_linenumber l_quantity l_extendedprice l_discount l_tax l_returnflag l_linestatus l_shipdate".split()))
_LINE = f"select 'lines' as sid, row_number() over (order by l_shipdate, {_LINE_KEYS}) - 1 as pos, epoch_us(l_shipdate) as t, round(l_extendedprice * 100)::bigint as v from lineitem"
_BLOCK = f"select 'blockmean' as sid, row_number() over (order by height) - 1 as pos, max(t) as t, height, 0::int as i, ((sum(v) * 100) // count(*))::bigint as v, '' as tags from ({_event_sql()}) group by height"
_STATE = f"select sid, pos, t, height, i, (sum(v) over (order by pos))::bigint as v, tags from ({_event_sql()})"
_CENTRED = f"select sid, pos, t, height, i, (sum(v - m) over (order by pos))::bigint as v, tags from (select *, (sum(v) over ()) // (count(*) over ()) as m from ({_event_sql()}))"
_TAIL = _event_sql(v="((round(value * 100)::hugeint * round(value * 100)::hugeint * round(value * 100)::hugeint) // 10000)::bigint")
STREAM_SQL = {"event_amt": _event_sql(), "event_tail": _TAIL, "rate_block": _BLOCK, "state_balance": _STATE, "state_centred": _CENTRED, "const_unit": _event_sql(v="1::bigint"), "order_price": _ORDER, "by_user": _event_sql("user_id::varchar"), "by_type": _event_sql("event_type")}

LENS = [20, 50, 100, 200, 500]


def _windows_sql(base: str, lengths: list[int] = LENS, count: int = 8, seed: int = 1) -> str:
    """CTEs r (records) and w (qid, sid, t_s, t_e, k, lo, hi, n)."""
    arr = "[" + ", ".join(map(str, lengths)) + "]"
    return f"""r as materialized ({base}), c as (select sid, count(*) as n from r group by sid),
g as (select q, {arr}[(q // {count}) + 1]::bigint as k from range({len(lengths) * count}) x(q)),
p as (select sid, n, q, k, {workload.draw_sql("q", seed)} % (n - k) as lo from g, c where k < n),
w0 as (select p.sid, p.n, q + {seed * 1_000_000} as qid, p.k, a.t as t_s, b.t as t_e from p join r a on a.sid = p.sid and a.pos = p.lo join r b on b.sid = p.sid and b.pos = p.lo + p.k - 1),
w as materialized (select w0.*, (select count(*) from r where r.sid = w0.sid and r.t < t_s) as lo, (select count(*) from r where r.sid = w0.sid and r.t <= t_e) - 1 as hi from w0)"""


def _agg_sql(cols: str) -> str:
    return f"select qid, {cols} from w left join r on r.sid = w.sid and r.t between w.t_s and w.t_e group by qid"


_FIVE = "coalesce(sum(v), 0)::bigint as s, count(v) as n, min(v) as mn, max(v) as mx, round(sum(v)::double / nullif(count(v), 0), 6) as avg"


def _windows(p: ex.Prepared, lengths: list[int] = LENS, count: int = 8, seed: int = 1) -> DataFrame:
    return workload.windows(p.records, lengths, count, seed)


def _located(p: ex.Prepared, q: DataFrame) -> DataFrame:
    return exact.locate(q, p.records, p.anchors)


# ---- streams and order ----------------------------------------------------------------------------------------------
@query("stream_records", f"select sid, pos, t, height, i, v, tags from ({STREAM_SQL['event_amt']})")
def stream_records(spark: SparkSession, d: str) -> DataFrame:
    return streams.stream(spark, d, "event_amt").select("sid", "pos", "t", "height", "i", "v", encoding.tags_text(F.col("tags")).alias("tags"))


for _name, _sql in STREAM_SQL.items():
    query(f"stream_{_name}", f"select sid, pos, t, v from ({_sql})")(lambda spark, d, n=_name: streams.stream(spark, d, n).select("sid", "pos", "t", "v"))


@query("positions_with_ties", f"select sid, pos, t, v from ({_LINE})")
def positions_with_ties(spark: SparkSession, d: str) -> DataFrame:
    return streams.stream(spark, d, "line_price", mode="range").select("sid", "pos", "t", "v")


@query("running_state_by_chunks", f"select sid, pos, v from ({_STATE})")
def running_state_by_chunks(spark: SparkSession, d: str) -> DataFrame:
    r = ordering.assign_positions(streams.STREAMS["event_amt"](spark, d), "range")
    return ordering.running_total(r, "chunk", 128).select("sid", "pos", "v")


@query("stream_stats", f"select sid, count(*) as n, median(gap) as median_gap, max(gap) as max_gap, round(stddev_pop(v) / abs(avg(v)), 6) as cv, median(abs(v)) as median_abs from (select *, t - lag(t) over (partition by sid order by pos) as gap from ({STREAM_SQL['by_type']})) group by sid")
def stream_stats(spark: SparkSession, d: str) -> DataFrame:
    return streams.statistics(streams.stream(spark, d, "by_type")).select("sid", "n", "median_gap", "max_gap", F.round("cv", 6).alias("cv"), "median_abs")


@query("block_headers", f"""with recursive b as (select height, max(t) as t, count(*) as n_tx, sha256(string_agg(sha256('L|' || sid || '|~|' || t || '|' || height || '|' || i || '|' || v || '|' || tags), '|' order by i)) as root from ({_event_sql()}) group by height),
k as (select *, row_number() over (order by height) as rn from b),
c as (select rn, height, t, n_tx, root, repeat('0', 64) as prev_hash, sha256('H|' || height || '|' || t || '|' || root || '|' || repeat('0', 64)) as hash from k where rn = 1
 union all select k.rn, k.height, k.t, k.n_tx, k.root, c.hash, sha256('H|' || k.height || '|' || k.t || '|' || k.root || '|' || c.hash) from c join k on k.rn = c.rn + 1)
select height, t, n_tx, root, prev_hash, hash from c""")
def block_headers(spark: SparkSession, d: str) -> DataFrame:
    return streams.blocks(streams.STREAMS["event_amt"](spark, d).withColumn("pos", F.lit(None).cast("long")))


@query("block_metrics", f"select height, sum(v)::bigint as s, min(v) as mn, max(v) as mx, count(*) as n from ({_event_sql()}) group by height")
def block_metrics(spark: SparkSession, d: str) -> DataFrame:
    r = streams.STREAMS["event_amt"](spark, d)
    parts = [streams.block_metric(r, m).select("height", F.col("v").alias(c)) for m, c in (("sum", "s"), ("min", "mn"), ("max", "mx"), ("count", "n"))]
    return parts[0].join(parts[1], "height").join(parts[2], "height").join(parts[3], "height")


for _by in ("value", "count"):
    query(f"top_source_{_by}", f"select sid, sum(v)::bigint as value, count(*) as count from ({STREAM_SQL['by_user']}) group by sid order by {_by} desc, sid limit 5")(lambda spark, d, by=_by: streams.top_source(streams.STREAMS["by_user"](spark, d), by, 5))


@query("stream_prefix", f"select sid, count(*) as n, sum(v)::bigint as s from ({_event_sql()}) where pos < 300 group by sid")
def stream_prefix(spark: SparkSession, d: str) -> DataFrame:
    return streams.prefix(streams.stream(spark, d, "event_amt"), 300).groupBy("sid").agg(F.count("*").alias("n"), F.sum("v").alias("s"))


@query("text_streams", "select 'doc_chars' as stream, lang as sid, count(*) as n, sum(n_chars)::bigint as s from documents group by lang union all select 'page_chars', 'pages', count(*), sum(length(html))::bigint from pages union all select 'first_component', 'emb', count(*), sum(floor(embedding[1]::double * 1000))::bigint from embeddings union all select 'turn_chars', conv_id::varchar, count(*), sum(length(text))::bigint from conversations group by conv_id union all select 'label_flags', 'labels', count(*), sum(quality * 2 + toxic)::bigint from labels union all select 'item_chars', 'items', count(*), sum(length(text))::bigint from benchmark")
def text_streams(spark: SparkSession, d: str) -> DataFrame:
    rows = [streams.STREAMS[x](spark, d).withColumn("stream", F.lit(x)) for x in ("doc_chars", "page_chars", "first_component", "turn_chars", "label_flags", "item_chars")]
    return reduce(DataFrame.unionByName, rows).groupBy("stream", "sid").agg(F.count("*").alias("n"), F.sum("v").alias("s"))


# ---- trees ----------------------------------------------------------------------------------------------------------
_LEAF = "sha256('L|' || sid || '|' || pos || '|' || t || '|' || height || '|' || i || '|' || v || '|' || tags)"


def _tree_sql(base: str, f: int = 2, levels: int = 20) -> str:
    """CTEs l0..lk and n (all levels, with lvl)."""
    bind = "eta || '|' || s || ':' || n || ':' || mn || ':' || mx || ':' || t_lo || ':' || t_hi || ':' || w"
    out = [f"l0 as materialized (select sid, pos as idx, v::hugeint as s, 1::hugeint as n, v as mn, v as mx, t as t_lo, t as t_hi, 0::hugeint as w, {_LEAF} as eta from ({base}))"]
    for k in range(levels):
        out.append(f"l{k + 1} as materialized (select sid, idx // {f} as idx, sum(s) as s, sum(n) as n, min(mn) as mn, max(mx) as mx, min(t_lo) as t_lo, max(t_hi) as t_hi, sum(w) as w, sha256('N|' || string_agg({bind}, '|' order by idx)) as eta from l{k} group by sid, idx // {f})")
    out.append("n as (" + " union all ".join(f"select {k} as lvl, * from l{k}" for k in range(levels + 1)) + ")")
    out.append("top as (select sid, min(lvl) as lvl from (select sid, lvl, count(*) as c from n group by sid, lvl) where c = 1 group by sid)")
    return ", ".join(out)


_ROOT = "select n.sid, n.lvl::int as depth, s::bigint as s, n.n::bigint as n, mn, mx, t_lo, t_hi, eta from n join top on top.sid = n.sid and top.lvl = n.lvl"


def _root(nodes: DataFrame) -> DataFrame:
    depth = nodes.groupBy("sid").agg(F.max("lvl").alias("depth"))
    return aggtree.roots(nodes).join(depth, "sid").select("sid", "depth", F.col("s").cast("long").alias("s"), "n", "mn", "mx", "t_lo", "t_hi", "eta")


@query("leaf_hashes", f"select pos, {_LEAF} as eta from ({_event_sql()})")
def leaf_hashes(spark: SparkSession, d: str) -> DataFrame:
    return aggtree.record_leaves(streams.stream(spark, d, "event_amt")).select(F.col("idx").alias("pos"), "eta")


@query("tree_levels", f"with {_tree_sql(_event_sql())} select n.sid, n.lvl::int as lvl, idx, s::bigint as s, n.n::bigint as n, mn, mx, t_lo, t_hi, eta from n join top using (sid) where n.lvl <= top.lvl")
def tree_levels(spark: SparkSession, d: str) -> DataFrame:
    return ex.prepare(spark, d, "event_amt").nodes.select("sid", "lvl", "idx", F.col("s").cast("long").alias("s"), "n", "mn", "mx", "t_lo", "t_hi", "eta")


for _name in ("order_price", "state_centred", "by_user", "rate_block"):
    query(f"tree_root_{_name}", f"with {_tree_sql(STREAM_SQL[_name])} {_ROOT}")(lambda spark, d, n=_name: _root(ex.prepare(spark, d, n).nodes))


@query("tree_root_fanout4", f"with {_tree_sql(_event_sql(), 4, 10)} {_ROOT}")
def tree_root_fanout4(spark: SparkSession, d: str) -> DataFrame:
    return _root(aggtree.build(aggtree.record_leaves(streams.stream(spark, d, "event_amt")), 4, 5))


@query("tree_root_by_groups", f"with {_tree_sql(STREAM_SQL['by_type'])} {_ROOT}")
def tree_root_by_groups(spark: SparkSession, d: str) -> DataFrame:
    return _root(aggtree.build_by_groups(aggtree.record_leaves(streams.stream(spark, d, "by_type"))))


@query("append_equals_rebuild", f"with {_tree_sql(_event_sql())} {_ROOT}")
def append_equals_rebuild(spark: SparkSession, d: str) -> DataFrame:
    r = streams.stream(spark, d, "event_amt")
    nodes = written(aggtree.build(aggtree.record_leaves(r.where("pos < 700"))))
    nodes = written(aggtree.append(nodes, aggtree.record_leaves(r.where("pos between 700 and 711"))))
    return _root(aggtree.append(nodes, aggtree.record_leaves(r.where("pos > 711"))))


@query("anchor_digest", f"with {_tree_sql(_event_sql())}, a as (select n.sid, n.n::bigint as n, eta, s || ':' || n.n || ':' || mn || ':' || mx || ':' || t_lo || ':' || t_hi || ':' || w as alpha from n join top on top.sid = n.sid and top.lvl = n.lvl) select sid, n as raw_n, eta as raw_root, sha256('A|' || sid || '|0|2|' || n || '|' || eta || '|' || alpha || '|~|~|~|~') as digest from a")
def anchor_digest(spark: SparkSession, d: str) -> DataFrame:
    return aggtree.anchor(ex.prepare(spark, d, "event_amt").nodes).select("sid", "raw_n", "raw_root", "digest")


# ---- covers and exact queries ---------------------------------------------------------------------------------------
_DESCENT = """, ext as (select w.*, (select min(e) from range(40) y(e) where (1::bigint << e) >= w.n)::int as top from w),
spans as (select qid, n, top, 'cover' as role, lo as a, hi as b from ext union all select qid, n, top, 'sibling', 0, lo - 2 from ext union all select qid, n, top, 'sibling', hi + 2, n - 1 from ext),
d as (select qid, n, role, a, b, top as lvl, 0::bigint as idx from spans where a <= b
 union all select qid, n, role, a, b, lvl - 1, idx * 2 + c from d, range(2) z(c)
 where lvl > 0 and not (idx << lvl >= a and least(((idx + 1) << lvl), n) - 1 <= b) and idx << lvl <= b and least(((idx + 1) << lvl), n) - 1 >= a and ((idx * 2 + c) << (lvl - 1)) < n),
keys as (select qid, role, lvl::int as lvl, idx from d where idx << lvl >= a and least(((idx + 1) << lvl), n) - 1 <= b)"""


@query("cover_keys", f"with recursive {_windows_sql(_event_sql())}{_DESCENT} select * from keys")
def cover_keys(spark: SparkSession, d: str) -> DataFrame:
    p = ex.prepare(spark, d, "event_amt")
    return cover.proof_keys(_located(p, _windows(p))).where("role != 'edge'").select("qid", "role", "lvl", "idx")


@query("cover_sizes", f"with recursive {_windows_sql(_event_sql())}{_DESCENT} select qid, count_if(role = 'cover') as cover, count_if(role = 'sibling') as siblings from keys group by qid")
def cover_sizes(spark: SparkSession, d: str) -> DataFrame:
    p = ex.prepare(spark, d, "event_amt")
    return cover.proof_keys(_located(p, _windows(p))).groupBy("qid").agg(F.count_if(F.col("role") == "cover").alias("cover"), F.count_if(F.col("role") == "sibling").alias("siblings"))


for _how in ("fence", "asof", "range"):
    query(f"locate_{_how}", f"with {_windows_sql(_ORDER)} select qid, lo, hi, n from w")(lambda spark, d, h=_how: exact.locate(_windows(p := ex.prepare(spark, d, "order_price")), p.records, p.anchors, h).select("qid", "lo", "hi", "n"))


@query("boundary_records", f"with {_windows_sql(_event_sql())} select qid, pos, t, v from w join r on r.sid = w.sid and r.pos in (w.lo - 1, w.hi + 1)")
def boundary_records(spark: SparkSession, d: str) -> DataFrame:
    p = ex.prepare(spark, d, "event_amt")
    return exact.prove_aggregate(_located(p, _windows(p)), p.nodes, p.records).where("role = 'edge'").select("qid", F.col("idx").alias("pos"), "rec.t", "rec.v")


for _name in ("event_amt", "order_price", "state_centred", "rate_block", "const_unit", "event_tail"):
    query(f"agg_{_name}", f"with {_windows_sql(STREAM_SQL[_name])} {_agg_sql(_FIVE)}")(lambda spark, d, n=_name: exact.aggregate(_located(p := ex.prepare(spark, d, n), _windows(p)), p.nodes).select("qid", "s", "n", "mn", "mx", "avg"))
for _f, _c in (("sum", "s"), ("count", "n"), ("min", "mn"), ("max", "mx"), ("avg", "avg")):
    query(f"agg_{_f}", f"with {_windows_sql(_event_sql())}, five as ({_agg_sql(_FIVE)}) select qid, {_c} from five")(lambda spark, d, c=_c: exact.aggregate(_located(p := ex.prepare(spark, d, "event_amt"), _windows(p)), p.nodes).select("qid", c))

_EDGES = "x as (select sid, min(t) as a, max(t) as b from r group by sid), y as (select x.*, (select min(t) from r where t > x.a) as a2 from x), w as (select y.sid, unnest([{'k': 0, 's': a - 100, 'e': a - 1}, {'k': 1, 's': b + 1, 'e': b + 100}, {'k': 2, 's': a, 'e': b}, {'k': 3, 's': a2, 'e': a2}, {'k': 4, 's': a + 1, 'e': a2 - 1}, {'k': 5, 's': a - 5, 'e': a2}, {'k': 6, 's': a2, 'e': b + 5}]) as q from y), ws as (select sid, q.k::bigint as qid, q.s as t_s, q.e as t_e from w)"


@query("agg_edge_cases", f"with r as ({_ORDER}), {_EDGES} {_agg_sql(_FIVE).replace('from w ', 'from ws w ')}")
def agg_edge_cases(spark: SparkSession, d: str) -> DataFrame:
    p = ex.prepare(spark, d, "order_price")
    return exact.aggregate(_located(p, workload.edge_cases(p.records)), p.nodes).select("qid", "s", "n", "mn", "mx", "avg")


@query("verify_edge_cases", f"with r as ({_ORDER}), {_EDGES} {_agg_sql('true as accepted, coalesce(sum(v), 0)::bigint as s, count(v) as n').replace('from w ', 'from ws w ')}")
def verify_edge_cases(spark: SparkSession, d: str) -> DataFrame:
    p = ex.prepare(spark, d, "order_price")
    return client.batch_verify(ex.wire(p, workload.edge_cases(p.records))).select("qid", "accepted", "s", "n")


_PER_STREAM = "x as (select sid, min(t) as a, max(t) as b from r group by sid), w as (select row_number() over (order by sid) - 1 as qid, sid, a + (b - a) // 4 as t_s, b - (b - a) // 4 as t_e from x)"
for _name in ("by_user", "by_type"):
    query(f"agg_all_{_name}", f"with r as ({STREAM_SQL[_name]}), {_PER_STREAM} select w.qid, w.sid, true as accepted, 'ok' as reason, coalesce(sum(v), 0)::bigint as s, count(v) as n, min(v) as mn, max(v) as mx from w left join r on r.sid = w.sid and r.t between t_s and t_e group by w.qid, w.sid")(lambda spark, d, n=_name: ex.multi_source(spark, d, n))

_ACCEPTED = "true as accepted, 'ok' as reason, coalesce(sum(v), 0)::bigint as s, count(v) as n, min(v) as mn, max(v) as mx"
for _name in ("event_amt", "order_price", "state_centred"):
    query(f"verify_agg_{_name}", f"with {_windows_sql(STREAM_SQL[_name])} {_agg_sql(_ACCEPTED)}")(lambda spark, d, n=_name: client.batch_verify(ex.wire(p := ex.prepare(spark, d, n), _windows(p))).drop("hashes"))


@query("verify_range", f"with {_windows_sql(_event_sql(), [20, 50])} {_agg_sql(_ACCEPTED)}")
def verify_range(spark: SparkSession, d: str) -> DataFrame:
    p = ex.prepare(spark, d, "event_amt")
    q = _windows(p, [20, 50])
    return client.batch_verify(exact.to_wire(exact.prove_range(_located(p, q), p.nodes, p.records), q, p.anchors)).drop("hashes")


@query("range_records", f"with {_windows_sql(_event_sql(), [20, 50])} select qid, pos, r.t, v from w join r on r.sid = w.sid and r.t between t_s and t_e")
def range_records(spark: SparkSession, d: str) -> DataFrame:
    p = ex.prepare(spark, d, "event_amt")
    return exact.prove_range(_located(p, _windows(p, [20, 50])), p.nodes, p.records).where("role = 'record'").select("qid", F.col("idx").alias("pos"), "rec.t", "rec.v")


def _tagged(name: str, predicate: Callable[[dict], bool], condition: str) -> None:
    sql = f"with {_windows_sql(_event_sql(), [50, 200])} select qid, true as accepted, coalesce(sum(v), 0)::bigint as s, count(v) as n from w left join r on r.sid = w.sid and r.t between w.t_s and w.t_e and ({condition}) group by qid"

    @query(name, sql)
    def run(spark: SparkSession, d: str) -> DataFrame:
        p = ex.prepare(spark, d, "event_amt")
        q = _windows(p, [50, 200])
        return client.batch_tagged(exact.to_wire(exact.prove_range(_located(p, q), p.nodes, p.records), q, p.anchors), predicate).select("qid", "accepted", "s", "n")


_tagged("tagged_equals", lambda t: t["event_type"] == "click", "event_type = 'click'")
_tagged("tagged_in", lambda t: t["event_type"] in ("click", "view", "purchase"), "event_type in ('click', 'view', 'purchase')")
_tagged("tagged_not_and_compare", lambda t: t["event_type"] != "click" and int(t["user_id"]) < 50, "event_type <> 'click' and user_id < 50")


def _tagged_by_column(name: str, condition: str, sql: str) -> None:
    """A predicate as a column over verified records."""

    @query(name, f"with {_windows_sql(_event_sql(), [50, 200])} select qid, true as accepted, coalesce(sum(v), 0)::bigint as s, count(v) as n from w left join r on r.sid = w.sid and r.t between w.t_s and w.t_e and ({sql}) group by qid")
    def run(spark: SparkSession, d: str) -> DataFrame:
        p = ex.prepare(spark, d, "event_amt")
        q = _windows(p, [50, 200])
        rows = client.batch_records(exact.to_wire(exact.prove_range(_located(p, q), p.nodes, p.records), q, p.anchors))
        kept = F.when(F.expr(condition), F.col("v"))
        return rows.groupBy("qid").agg(F.bool_and("accepted").alias("accepted"), F.coalesce(F.sum(kept), F.lit(0)).alias("s"), F.count(kept).alias("n"))


_tagged_by_column("tagged_or", "tags['event_type'] = 'click' or cast(tags['user_id'] as bigint) < 20", "event_type = 'click' or user_id < 20")
_tagged_by_column("tagged_like_or_not", "tags['event_type'] like '%i%' or not cast(tags['user_id'] as bigint) between 10 and 90", "event_type like '%i%' or not user_id between 10 and 90")


@query("worked_example", f"with r as ({STREAM_SQL['by_user']}), w as (select sid, min(t) filter (pos = 0) as t_s, max(t) filter (pos <= 2) as t_e from r group by sid) select w.sid, true as accepted, sum(v)::bigint as total, count(*) as cnt, round(sum(v)::double / count(*), 6) as mean from w join r on r.sid = w.sid and r.t between t_s and t_e group by w.sid")
def worked_example(spark: SparkSession, d: str) -> DataFrame:
    return ex.worked_example(spark, d)


# ---- sliding windows ------------------------------------------------------------------------------------------------
def _slides(spark: SparkSession, d: str) -> tuple[ex.Prepared, DataFrame]:
    p = ex.prepare(spark, d, "event_amt")
    return p, written(workload.sliding(spark, ex.sliding_sequences(p, p.n // 20, (10, 30, 50), 20)))


_SLIDE = f"r as ({_event_sql()}), x as (select sid, min(t) as a, trunc((max(t) - min(t)) / count(*)::double * (count(*) // 20))::bigint as wd from r group by sid), s as (select sid, a, wd, unnest([10, 30, 50])::bigint as seq_id from x), w as (select seq_id, i, sid, a + wd + i * trunc(wd * seq_id / 100.0)::bigint as t_s, a + 2 * wd - 1 + i * trunc(wd * seq_id / 100.0)::bigint as t_e from s, range(20) y(i))"


for _cache in ("all", "current"):

    @query(f"verify_sliding_{_cache}", f"with {_SLIDE} select seq_id, w.i, true as accepted, coalesce(sum(v), 0)::bigint as s, count(v) as n from w left join r on r.t between t_s and t_e group by seq_id, w.i")
    def verify_sliding(spark: SparkSession, d: str, cache: str = _cache) -> DataFrame:
        p, w = _slides(spark, d)
        vo = written(exact.prove_aggregate(_located(p, w), p.nodes, p.records))
        return sliding.verify_sequence(vo, w, p.anchors, cache)


@query("sliding_avg", f"with {_SLIDE} select seq_id, w.i, round(sum(v)::double / nullif(count(v), 0), 6) as avg from w left join r on r.t between t_s and t_e group by seq_id, w.i")
def sliding_avg(spark: SparkSession, d: str) -> DataFrame:
    p, w = _slides(spark, d)
    return exact.aggregate(_located(p, w), p.nodes).join(w.select("qid", "seq_id", "i"), "qid").select("seq_id", "i", "avg")


@query("sliding_cost")
def sliding_cost(spark: SparkSession, d: str) -> DataFrame:
    return ex.sliding_cost(spark, d)


# ---- segments and intervals -----------------------------------------------------------------------------------------
for _name in ("event_amt", "state_balance", "order_price"):
    query(f"seg_certified_{_name}", f"select count(*) as records, 0::bigint as violations from ({STREAM_SQL[_name]})")(lambda spark, d, n=_name: (p := ex.prepare(spark, d, n)).segments.agg(F.sum("c").alias("records")).crossJoin(F.broadcast(segments.replay(p.segments, p.records).agg(F.count_if(~F.col("valid")).alias("violations")))))


@query("seg_bad_encoders", "select unnest(['arrival_bound', 'count', 'gap', 'overlap', 'slope', 'value_bound']) as kind, true as rejected")
def seg_bad_encoders(spark: SparkSession, d: str) -> DataFrame:
    p = ex.prepare(spark, d, "event_amt")
    parts = [segments.replay(segments.bad_encoder(p.segments, k), p.records).agg(F.lit(k).alias("kind"), (F.count_if(~F.col("valid")) > 0).alias("rejected")) for k in segments.CORRUPTIONS]
    out = parts[0]
    for x in parts[1:]:
        out = out.unionByName(x)
    return out


@query("seg_fits")
def seg_fits(spark: SparkSession, d: str) -> DataFrame:
    """Segment counts: optimal lines against lines pinned to the first record, residual against flat bounds."""
    p = ex.prepare(spark, d, "rate_block")
    rows = [(fit, bound, segments.greedy(p.records, p.budgets, fit, bound=bound)) for fit in ("hull", "cone") for bound in ("residual", "budget")]
    out = [s.agg(F.lit(f).alias("fit"), F.lit(b).alias("bound"), F.count("*").alias("s"), F.max("eps_v").alias("cap")) for f, b, s in rows]
    return out[0].unionByName(out[1]).unionByName(out[2]).unionByName(out[3])


def _inside_sql(base: str, f: str) -> str:
    value = {"SUM": "coalesce(sum(v), 0)::double", "COUNT": "count(v)::double", "MIN": "min(v)::double", "MAX": "max(v)::double", "AVG": "round(sum(v)::double / count(v), 6)"}[f]
    return f"with {_windows_sql(base)} {_agg_sql(f'{value} as exact, true as accepted, true as inside')}"


def _inside(spark: SparkSession, d: str, name: str, f: str) -> DataFrame:
    p = ex.prepare(spark, d, name)
    value = F.round("exact", 6) if f == "AVG" else F.col("exact")
    return ex.intervals(p, _windows(p)).where(F.col("f") == f).select("qid", value.alias("exact"), "accepted", "inside")


for _f in client.AGGREGATES:
    query(f"approx_{_f.lower()}", _inside_sql(_BLOCK, _f))(lambda spark, d, f=_f: _inside(spark, d, "rate_block", f))
for _name in ("state_centred", "event_amt", "const_unit", "order_price", "event_tail"):
    query(f"approx_sum_{_name}", _inside_sql(STREAM_SQL[_name], "SUM"))(lambda spark, d, n=_name: _inside(spark, d, n, "SUM"))


@query("approx_positions", f"select sid, pos, true as v_inside, true as t_inside from ({_BLOCK})")
def approx_positions(spark: SparkSession, d: str) -> DataFrame:
    p = ex.prepare(spark, d, "rate_block")
    r = approx.reconstruct(p.segments).join(p.records.select("sid", "pos", "v", "t"), ["sid", "pos"])
    scaled = lambda c, k: F.col(c).cast("decimal(19,0)") * k
    return r.select("sid", "pos", scaled("v", lines.V).between(F.col("v_lo"), F.col("v_hi")).alias("v_inside"), scaled("t", lines.T).between(F.col("t_lo"), F.col("t_hi")).alias("t_inside"))


_CENTS = "round(value * 100)::bigint"


@query("line_closed_forms", f"select event_id, a, sum(a * p + 3)::bigint as s, count(*) as n, min(a * p + 3) as mn, max(a * p + 3) as mx from (select event_id, {_CENTS} - 5000 as a from events), range(2, 9) y(p) group by event_id, a")
def line_closed_forms(spark: SparkSession, d: str) -> DataFrame:
    """Positions 2 to 8 of a line per event, whose slope is the event's value less 50."""
    g = read_table(spark, d, "events", ["event_id", "value"]).select("event_id", (streams.cents("value") - 5000).alias("a"))
    got = lines.line_aggregates(F.col("a").cast("decimal(18,0)"), F.lit(3).cast("decimal(18,0)"), F.lit(2).cast("decimal(9,0)"), F.lit(8).cast("decimal(9,0)"))
    return g.select("event_id", "a", *[c.cast("long").alias(k) for k, c in got.items()])


@query("arrival_inversion", "with g as (select mu, x, (select min(p) from range(0, 400) y(p) where mu * p + 7 >= x) as p from range(1, 6) a(mu), range(7, 100) b(x)) select event_id, mu, x, p from events join g on mu = 1 + user_id % 5 and x = 7 + event_id % 93")
def arrival_inversion(spark: SparkSession, d: str) -> DataFrame:
    g = read_table(spark, d, "events", ["event_id", "user_id"]).select("event_id", (F.col("user_id") % 5 + 1).alias("mu"), (F.col("event_id") % 93 + 7).alias("x"))
    return g.select("event_id", "mu", "x", lines.invert_arrival(F.col("mu"), F.lit(7), F.col("x")).cast("long").alias("p"))


@query("undecided_runs")
def undecided_runs(spark: SparkSession, d: str) -> DataFrame:
    p = ex.prepare(spark, d, "rate_block")
    q = _windows(p)
    k = ex.intervals(p, q).where("f = 'COUNT'").select("qid", "undecided", "k_formula")
    return k.join(approx.edge_set(p.segments, q), "qid").join(approx.edge_set(p.segments, q, "tau").select("qid", F.col("edge").alias("edge_tau")), "qid")


@query("seg_external_encoder", f"select count(*) as records, 0::bigint as violations from ({_BLOCK})")
def seg_external_encoder(spark: SparkSession, d: str) -> DataFrame:
    """Segments of an encoder known by its table only, certified before use."""
    p = ex.prepare(spark, d, "rate_block")
    other = segments.from_table(written(segments.greedy(p.records, p.budgets, "cone").withColumn("maker", F.lit("outside"))))
    return segments.replay(other, p.records).agg(F.count_if(~F.col("valid")).alias("violations")).crossJoin(other.agg(F.sum("c").alias("records"))).select("records", "violations")


@query("value_share")
def value_share(spark: SparkSession, d: str) -> DataFrame:
    p = ex.prepare(spark, d, "rate_block")
    return costs.value_share(ex.intervals(p, _windows(p)).withColumn("stream", F.lit("rate_block")))


for _name in streams.MAIN:
    query(f"approx_range_{_name}", f"with {_windows_sql(STREAM_SQL[_name], [20, 50])} select qid, pos, true as accepted, true as v_inside, true as t_inside from w join r on r.sid = w.sid and r.t between t_s and t_e")(lambda spark, d, n=_name: ex.retrieved(p := ex.prepare(spark, d, n), _windows(p, [20, 50])))

for _f in ("MIN", "MAX"):

    @query(f"approx_{_f.lower()}_opened", _inside_sql(_BLOCK, _f))
    def approx_opened(spark: SparkSession, d: str, f: str = _f) -> DataFrame:
        """Extremes whose slack comes from the opened segments instead of the anchored cap."""
        p = ex.prepare(spark, d, "rate_block")
        q = _windows(p)
        found = client.batch_approx(ex.range_wire(p, q), "opened").join(q.select("qid", "sid"), "qid")
        return costs.containment(found, exact.aggregate(_located(p, q), p.nodes)).where(F.col("f") == f).select("qid", "exact", "accepted", "inside")


# ---- policies -------------------------------------------------------------------------------------------------------
@query("region_touches", f"with {_windows_sql(_BLOCK)}, z as (select sid, least(lo // (n // 16), 15) as a, least(hi // (n // 16), 15) as b from w), y as (select sid, a, b, unnest(range(a, b + 1)) as region from z) select sid, region, count(*) as f_touch, sum((region = a)::int + (region = b)::int)::bigint as f_edge from y group by sid, region")
def region_touches(spark: SparkSession, d: str) -> DataFrame:
    p = ex.prepare(spark, d, "rate_block")
    return workload.touch_counts(_located(p, _windows(p)), p.n)


_SKEW = f"r as ({_BLOCK}), c as (select sid, count(*) as n from r group by sid), q as (select x.q, {workload.draw_sql('x.q', 1)} % 1000 as u, {workload.draw_sql('x.q', 2)} as ra from range(100) x(q)), w as (select q as qid, sid, case when u < 750 then least(5 * greatest(n // 16, 1) + ra % greatest(n // 16, 1), n - 21) else ra % (n - 20) end as lo from q, c)"


@query("skewed_workload", f"with {_SKEW} select qid, sid, lo, lo + 19 as hi from w")
def skewed_workload(spark: SparkSession, d: str) -> DataFrame:
    return workload.skewed(ex.prepare(spark, d, "rate_block").records, 0.75, 100, 20).select("qid", "sid", "lo", "hi")


@query("policy_allocations")
def policy_allocations(spark: SparkSession, d: str) -> DataFrame:
    found = ex.policies(ex.prepare(spark, d, "rate_block"), 0.75, 20)
    rows = [b.withColumn("policy", F.lit(k)) for k, (b, _) in found.items()]
    return rows[0].unionByName(rows[1]).unionByName(rows[2]).unionByName(rows[3]).select("policy", "region", "eps_v", "eps_t")


@query("policy_mean_is_uniform", "select unnest(['adversarial', 'edge_aware', 'learned', 'uniform']) as policy, 1.0::double as mean_factor")
def policy_mean_is_uniform(spark: SparkSession, d: str) -> DataFrame:
    p = ex.prepare(spark, d, "rate_block")
    base = budget.defaults(p.stats).select("sid", F.col("eps_v").alias("base"))
    return policy_allocations(spark, d).crossJoin(F.broadcast(base)).groupBy("policy").agg(F.round(F.avg(F.col("eps_v") / F.col("base")), 6).alias("mean_factor"))


_SPANS = [3_600_000_000, 86_400_000_000]


@query("windows_by_time", f"with r as ({_event_sql()}), e as (select sid, min(t) as a, max(t) as b from r group by sid), g as (select q, {_SPANS}[(q // 5) + 1]::bigint as k from range(10) x(q)), w as (select q + 1000000 as qid, sid, a + ({workload.draw_sql('q', 1)} * ((b - a) // 2147483647 + 1)) % greatest(b - a, 1) as t_s, k from e, g) select qid, coalesce(sum(v), 0)::bigint as s, count(v) as n from w left join r on r.sid = w.sid and r.t between t_s and t_s + k - 1 group by qid")
def windows_by_time(spark: SparkSession, d: str) -> DataFrame:
    p = ex.prepare(spark, d, "event_amt")
    return exact.aggregate(_located(p, written(workload.by_time(p.records, _SPANS, 5))), p.nodes).select("qid", "s", "n")


# ---- baselines and costs --------------------------------------------------------------------------------------------
_SCAN = "coalesce(sum(v), 0)::bigint as s, count(v) as n, min(v) as mn, max(v) as mx"


@query("baseline_scan", f"with {_windows_sql(_event_sql())} {_agg_sql(_SCAN)}")
def baseline_scan(spark: SparkSession, d: str) -> DataFrame:
    p = ex.prepare(spark, d, "event_amt")
    return baselines.scan(_located(p, _windows(p)), p.records).drop("sid")


@query("baseline_redownload", f"with {_windows_sql(_event_sql())} {_agg_sql(_SCAN + ', count(v) * 16 as bytes')}")
def baseline_redownload(spark: SparkSession, d: str) -> DataFrame:
    p = ex.prepare(spark, d, "event_amt")
    return baselines.redownload(_located(p, _windows(p)), p.records).drop("sid")


@query("baseline_block_scan", f"with {_windows_sql(_event_sql())} select qid, count(distinct height) as blocks, sum(v)::bigint as s, count(v) as n from w join r on r.sid = w.sid and r.t between w.t_s and w.t_e group by qid")
def baseline_block_scan(spark: SparkSession, d: str) -> DataFrame:
    p = ex.prepare(spark, d, "event_amt")
    return baselines.block_scan(_windows(p), p.records)


@query("baseline_paths", f"with {_windows_sql(_event_sql(), [20, 50])}, l as (select qid, n, unnest(range(lo, hi + 1)) as pos, (select min(e) from range(40) y(e) where (1::bigint << e) >= n) as top from w), k as (select qid, n, pos, unnest(range(0, top)) as lvl from l) select qid, count_if(lvl = 0) as records, sum(case when ((pos >> lvl) # 1) << lvl < n then 1 else 0 end)::bigint as path_nodes from k group by qid".replace("(pos >> lvl) # 1", "xor(pos >> lvl, 1)"))
def baseline_paths(spark: SparkSession, d: str) -> DataFrame:
    p = ex.prepare(spark, d, "event_amt")
    return baselines.per_record_paths(_located(p, _windows(p, [20, 50]))).select("qid", "records", "path_nodes")


@query("baseline_paths_verified", f"with {_windows_sql(_event_sql(), [20, 50])} {_agg_sql('true as accepted, coalesce(sum(v), 0)::bigint as s, count(v) as n')}")
def baseline_paths_verified(spark: SparkSession, d: str) -> DataFrame:
    """A path per record, shipped and checked."""
    p = ex.prepare(spark, d, "event_amt")
    q = written(_windows(p, [20, 50]))
    entries = baselines.prove_paths(_located(p, q), p.nodes, p.records)
    return client.batch_paths(baselines.paths_wire(entries, q, p.anchors)).select("qid", "accepted", "s", "n")


@query("baseline_paths_shipped", f"with {_windows_sql(_event_sql(), [20, 50])}, l as (select qid, n, unnest(range(greatest(lo - 1, 0), least(hi + 1, n - 1) + 1)) as pos, (select min(e) from range(40) y(e) where (1::bigint << e) >= n) as top from w), k as (select qid, n, pos, unnest(range(0, top)) as lvl from l) select qid, count_if(lvl = 0) as records, sum(case when (xor(pos >> lvl, 1)) << lvl < n then 1 else 0 end)::bigint as path_nodes from k group by qid")
def baseline_paths_shipped(spark: SparkSession, d: str) -> DataFrame:
    """Path nodes that really travel, with the two records beside the window."""
    p = ex.prepare(spark, d, "event_amt")
    entries = baselines.prove_paths(_located(p, _windows(p, [20, 50])), p.nodes, p.records)
    return entries.select("qid", F.size("entries").cast("long").alias("records"), F.aggregate("entries", F.lit(0).cast("long"), lambda n, e: n + F.size(e["path"])).alias("path_nodes"))


@query("baseline_leaves", f"with recursive {_windows_sql(_event_sql(), [20, 50])}{_DESCENT} select w.qid, (hi - lo + 1) as records, (select count(*) from keys where keys.qid = w.qid and role = 'sibling') as siblings from w")
def baseline_leaves(spark: SparkSession, d: str) -> DataFrame:
    p = ex.prepare(spark, d, "event_amt")
    vo = baselines.leaf_fold(_located(p, _windows(p, [20, 50])), p.nodes, p.records)
    return vo.groupBy("qid").agg(F.count_if(F.col("role") == "record").alias("records"), F.count_if(F.col("role") == "sibling").alias("siblings"))


_EDGE_COUNT = "((lo > 0)::int + (hi < n - 1)::int)"


@query("cost_bytes", f"with recursive {_windows_sql(_event_sql())}{_DESCENT}, k as (select qid, count(*) as nodes from keys group by qid) select w.qid, nodes + {_EDGE_COUNT} as parts, nodes * 64 + {_EDGE_COUNT} * 16 as bytes from w join k using (qid)")
def cost_bytes(spark: SparkSession, d: str) -> DataFrame:
    p = ex.prepare(spark, d, "event_amt")
    return costs.vo_bytes(exact.prove_aggregate(_located(p, _windows(p)), p.nodes, p.records))


@query("cost_touched", f"with recursive {_windows_sql(_event_sql())}{_DESCENT} select w.qid, (select count(*) from keys where keys.qid = w.qid and role = 'cover') as touched, hi - lo + 1 as scanned from w")
def cost_touched(spark: SparkSession, d: str) -> DataFrame:
    p = ex.prepare(spark, d, "event_amt")
    loc = written(_located(p, _windows(p)))
    return costs.touched(exact.prove_aggregate(loc, p.nodes, p.records)).join(loc, "qid").select("qid", "touched", (F.col("hi") - F.col("lo") + 1).alias("scanned"))


@query("cost_transfer", f"with {_windows_sql(_event_sql())} select qid, (hi - lo + 1) * 16 as client_side, 8::bigint as chain_side from w")
def cost_transfer(spark: SparkSession, d: str) -> DataFrame:
    p = ex.prepare(spark, d, "event_amt")
    return costs.transfer(baselines.scan(_located(p, _windows(p)), p.records))


_KINDS = sorted([*attacks.EXACT, *attacks.RANGE, *attacks.APPROX, *attacks.APPROX_RANGE])


@query("tamper_matrix", "select stream, kind, 20::bigint as attempts, 20::bigint as rejected, 20::bigint as as_expected from (select unnest([" + ", ".join(f"'{k}'" for k in _KINDS) + "]) as kind), (select unnest([" + ", ".join(f"'{k}'" for k in streams.MAIN) + "]) as stream)")
def tamper_matrix(spark: SparkSession, d: str) -> DataFrame:
    return ex.tamper(spark, d)


for _name, _make in (("experiment_stream_table", ex.stream_table), ("experiment_touched", ex.touched), ("experiment_proof_size", ex.proof_size), ("experiment_break_even", ex.break_even), ("experiment_widths", ex.widths), ("experiment_value_blindness", ex.value_blindness), ("experiment_scale", ex.scale), ("experiment_budget_sweep", ex.budget_sweep), ("experiment_halve", ex.halve), ("experiment_boundary", ex.boundary), ("experiment_encoders", ex.encoder_study), ("experiment_range_size", ex.range_size), ("experiment_agg_bytes", ex.agg_vo), ("experiment_repeats", ex.repeats), ("experiment_percentile_budget", ex.percentile_contrast), ("experiment_tamper", ex.tamper), ("experiment_latency", ex.latency), ("experiment_client_time", ex.client_time), ("experiment_construction", ex.construction)):
    query(_name)(_make)


@query("planner_choice", "with st as (select event_type, count(*) as n, count(*) // (2 + length(event_type) % 3) as s from events group by event_type) select event_id as qid, case when event_id % 3 = 0 then 'exact' when event_id % 3 = 2 and n * 16 <= s * 48 then 'exact' when event_id % 3 = 1 and 4 * user_id > 3000 then 'exact' else 'approximate' end as path from events join st using (event_type)")
def planner_choice(spark: SparkSession, d: str) -> DataFrame:
    """A query per event: a sum over as many records as its user's number, or a range, of its type's stream."""
    e = _t(spark, d, "events", "event_id", "user_id", "event_type").withColumnRenamed("event_type", "sid")
    kind = F.col("event_id") % 3
    q = e.select(F.col("event_id").alias("qid"), "sid", F.when(kind == 2, "RANGE").otherwise("SUM").alias("f"), (kind == 0).alias("exact"), F.col("user_id").alias("k"), F.lit(3000.0).alias("max_width"))
    stats = e.groupBy("sid").agg(F.count("*").alias("n")).select("sid", "n", F.expr("n div (2 + length(sid) % 3)").alias("s"), F.lit(2.0).alias("eps_v"))
    return planner.choose(q, stats).select("qid", "path")


# ---- uses -----------------------------------------------------------------------------------------------------------
@query("use_case_price_range", "with r as (select l_suppkey::varchar as sid, epoch_us(l_shipdate) as t, round(l_extendedprice * 100)::bigint as v from lineitem), " + _PER_STREAM + " select w.sid, min(v) as mn, max(v) as mx from w left join r on r.sid = w.sid and r.t between t_s and t_e group by w.sid")
def use_case_price_range(spark: SparkSession, d: str) -> DataFrame:
    return ex.multi_source(spark, d, "by_supplier").where("accepted").select("sid", "mn", "mx")


@query("use_case_customer_audit", "with r as (select o_custkey::varchar as sid, epoch_us(o_orderdate) as t, round(o_totalprice * 100)::bigint as v from orders), " + _PER_STREAM + " select w.sid, coalesce(sum(v), 0)::bigint as s, count(v) as n from w left join r on r.sid = w.sid and r.t between t_s and t_e group by w.sid")
def use_case_customer_audit(spark: SparkSession, d: str) -> DataFrame:
    return ex.multi_source(spark, d, "by_customer").where("accepted").select("sid", "s", "n")


# ---- streaming ------------------------------------------------------------------------------------------------------
@query("streamed_equals_batch", f"with {_tree_sql(STREAM_SQL['by_type'])} {_ROOT}")
def streamed_equals_batch(spark: SparkSession, d: str) -> DataFrame:
    source, target = scratch(spark), scratch(spark)
    r = streams.STREAMS["by_type"](spark, d)
    cut = r.agg(F.max("height")).first()[0] // 2
    for part in (r.where(F.col("height") <= cut), r.where(F.col("height") > cut)):
        part.coalesce(1).write.mode("append").parquet(source)
    batches = streaming.ingest(spark, source, target)
    return _root(streaming.TreeSink(target).nodes(spark, batches))


for _kind in ("tumbling", "sliding", "session"):
    _sql = {
        "tumbling": "select t_lo, t_lo + 86400000000 as t_hi, sum(v)::bigint as s, count(*) as n from (select epoch_us(ts) - epoch_us(ts) % 86400000000 as t_lo, round(value * 100)::bigint as v from events) group by t_lo",
        "sliding": "select t_lo, t_lo + 86400000000 as t_hi, sum(v)::bigint as s, count(*) as n from (select epoch_us(ts) - epoch_us(ts) % 43200000000 - 43200000000 * k as t_lo, round(value * 100)::bigint as v from events, range(2) x(k)) group by t_lo",
        "session": "select min(t) as t_lo, max(t) + 1800000000 as t_hi, sum(v)::bigint as s, count(*) as n from (select *, sum(fresh) over (order by t) as g from (select epoch_us(ts) as t, round(value * 100)::bigint as v, case when epoch_us(ts) - lag(epoch_us(ts)) over (order by ts) < 1800000000 then 0 else 1 end as fresh from events)) group by g",
    }[_kind]
    query(f"window_{_kind}", _sql)(lambda spark, d, k=_kind: streaming.window_agg(read_table(spark, d, "events", ["ts", "value"]).select(F.col("ts").cast("timestamp").alias("ts"), streams.cents("value").alias("v")), "ts", "v", k, "30 minutes" if k == "session" else "1 day", "12 hours"))


@query("stream_enrich", "select event_id, p_brand, round(value * 100)::bigint as v from events left join part on p_partkey = user_id")
def stream_enrich(spark: SparkSession, d: str) -> DataFrame:
    """A stream joined with a static table, written in micro-batches."""
    source, target = scratch(spark), scratch(spark)
    e = read_table(spark, d, "events", ["event_id", "user_id", "value"]).select("event_id", F.col("user_id").alias("p_partkey"), streams.cents("value").alias("v"))
    e.write.parquet(source)
    out = streaming.enrich(spark.readStream.schema(e.schema).parquet(source), read_table(spark, d, "part", ["p_partkey", "p_brand"]), "p_partkey").select("event_id", "p_brand", "v")
    run = out.writeStream.format("parquet").option("path", target).option("checkpointLocation", f"{target}-state").trigger(availableNow=True).start()
    run.awaitTermination()
    return spark.read.schema(out.schema).parquet(target)


@query("dedup_events", "select count(*) as n from events")
def dedup_events(spark: SparkSession, d: str) -> DataFrame:
    e = read_table(spark, d, "events", ["event_id"])
    return e.unionByName(e).dropDuplicates(["event_id"]).agg(F.count("*").alias("n"))


# ---- functions in SQL -----------------------------------------------------------------------------------------------
@query("udtf_cover", f"with recursive {_windows_sql(_event_sql(), [20, 50])}{_DESCENT} select qid, lvl, idx from keys where role = 'cover'")
def udtf_cover(spark: SparkSession, d: str) -> DataFrame:
    udf.register(spark)
    p = ex.prepare(spark, d, "event_amt")
    _located(p, _windows(p, [20, 50])).createOrReplaceTempView("located_windows")
    return spark.sql("select qid, c.lvl, c.idx from located_windows w, lateral cover_nodes(w.lo, w.hi, w.n, 2) c")


@query("udf_verify", f"with {_windows_sql(_event_sql())} {_agg_sql('true as accepted, coalesce(sum(v), 0)::bigint as s, count(v) as n, min(v) as mn, max(v) as mx')}")
def udf_verify(spark: SparkSession, d: str) -> DataFrame:
    """The client's check as a function in SQL."""
    udf.register(spark)
    p = ex.prepare(spark, d, "event_amt")
    return spark.sql("select qid, x.accepted, x.s, x.n, x.mn, x.mx from (select qid, verify_window(sid, t_s, t_e, proof, anchor) as x from {wire})", wire=ex.wire(p, _windows(p)))


@query("udaf_fold", f"with {_windows_sql(_event_sql())} {_agg_sql('coalesce(sum(v), 0)::bigint as s')}")
def udaf_fold(spark: SparkSession, d: str) -> DataFrame:
    p = ex.prepare(spark, d, "event_amt")
    vo = exact.prove_aggregate(_located(p, _windows(p)), p.nodes, p.records).where("role = 'cover'")
    return vo.groupBy("qid").agg(udf.fold_sum(F.col("alpha.s").cast("long")).alias("s"))


# ---- relational operators -------------------------------------------------------------------------------------------
def _t(spark: SparkSession, d: str, name: str, *columns: str) -> DataFrame:
    return read_table(spark, d, name, list(columns) or None)


@query("scan_filter", "select event_id, event_type from events where epoch_us(ts) between 1704153600000000 and 1704326400000000 and event_type in ('click', 'view') and user_id is not null")
def scan_filter(spark: SparkSession, d: str) -> DataFrame:
    e = _t(spark, d, "events", "event_id", "ts", "event_type", "user_id")
    lo, hi = F.lit("2024-01-02").cast("timestamp_ntz"), F.lit("2024-01-04").cast("timestamp_ntz")
    return e.where(F.col("ts").between(lo, hi) & F.col("event_type").isin("click", "view") & F.col("user_id").isNotNull()).select("event_id", "event_type")


@query("join_semi", "select c_custkey from customer where c_custkey in (select o_custkey from orders where o_totalprice > 200000)")
def join_semi(spark: SparkSession, d: str) -> DataFrame:
    big = _t(spark, d, "orders").where("o_totalprice > 200000").select(F.col("o_custkey").alias("c_custkey"))
    return _t(spark, d, "customer", "c_custkey").join(big, "c_custkey", "left_semi")


@query("join_anti", "select c_custkey from customer where c_custkey not in (select o_custkey from orders)")
def join_anti(spark: SparkSession, d: str) -> DataFrame:
    return _t(spark, d, "customer", "c_custkey").join(_t(spark, d, "orders").select(F.col("o_custkey").alias("c_custkey")), "c_custkey", "left_anti")


for _how in ("left", "right", "full"):
    query(f"join_{_how}", f"select c_custkey, count(o_orderkey) as n from customer {_how} join orders on c_custkey = o_custkey group by c_custkey")(lambda spark, d, h=_how: _t(spark, d, "customer", "c_custkey").join(_t(spark, d, "orders", "o_orderkey", "o_custkey"), F.col("c_custkey") == F.col("o_custkey"), h).groupBy("c_custkey").agg(F.count("o_orderkey").alias("n")))


@query("join_merge_orders", "select o_orderkey, count(*) as n, sum(round(l_extendedprice * 100)::bigint)::bigint as s from orders join lineitem on l_orderkey = o_orderkey group by o_orderkey")
def join_merge_orders(spark: SparkSession, d: str) -> DataFrame:
    li = _t(spark, d, "lineitem", "l_orderkey", "l_extendedprice").select(F.col("l_orderkey").alias("o_orderkey"), streams.cents("l_extendedprice").alias("v"))
    return relops.join_merge(_t(spark, d, "orders", "o_orderkey"), li, ["o_orderkey"]).groupBy("o_orderkey").agg(F.count("*").alias("n"), F.sum("v").alias("s"))


@query("join_hash_parts", "select p_brand, count(*) as n from lineitem join part on p_partkey = l_partkey group by p_brand")
def join_hash_parts(spark: SparkSession, d: str) -> DataFrame:
    li = _t(spark, d, "lineitem", "l_partkey").withColumnRenamed("l_partkey", "p_partkey")
    return relops.join_hash(li, _t(spark, d, "part", "p_partkey", "p_brand"), ["p_partkey"]).groupBy("p_brand").agg(F.count("*").alias("n"))


@query("join_star_region", "select r_name, o_orderstatus, count(*) as n, sum(round(o_totalprice * 100)::bigint)::bigint as s from orders join customer on c_custkey = o_custkey join nation on n_nationkey = c_nationkey join region on r_regionkey = n_regionkey group by all")
def join_star_region(spark: SparkSession, d: str) -> DataFrame:
    o = _t(spark, d, "orders", "o_custkey", "o_orderstatus", "o_totalprice").withColumnRenamed("o_custkey", "c_custkey")
    c = relops.join_broadcast(_t(spark, d, "customer", "c_custkey", "c_nationkey").withColumnRenamed("c_nationkey", "n_nationkey"), _t(spark, d, "nation", "n_nationkey", "n_regionkey").withColumnRenamed("n_regionkey", "r_regionkey"), ["n_nationkey"])
    c = relops.join_broadcast(c, _t(spark, d, "region"), ["r_regionkey"])
    return o.join(c, "c_custkey").groupBy("r_name", "o_orderstatus").agg(F.count("*").alias("n"), F.sum(streams.cents("o_totalprice")).alias("s"))


@query("join_grid_budgets", "select sid, f from (select distinct event_type as sid from events), (select unnest([0.05, 0.1, 0.2])::double as f)")
def join_grid_budgets(spark: SparkSession, d: str) -> DataFrame:
    return relops.grid(_t(spark, d, "events", "event_type").select(F.col("event_type").alias("sid")).distinct(), spark.createDataFrame([(0.05,), (0.1,), (0.2,)], "f double"))


@query("join_range_bucketed", f"with {_windows_sql(_event_sql())} select qid, count(*) as n from w join r on r.sid = w.sid and r.t between w.t_s and w.t_e group by qid")
def join_range_bucketed(spark: SparkSession, d: str) -> DataFrame:
    p = ex.prepare(spark, d, "event_amt")
    return relops.join_range(p.records.select("sid", "t"), _windows(p).select("qid", "sid", "t_s", "t_e"), ["sid"], "t", "t_s", "t_e", 3_600_000_000).groupBy("qid").agg(F.count("*").alias("n"))


# keys without a match on the other side give null
for _dir, _op in (("backward", ">="), ("forward", "<=")):
    query(f"join_asof_{_dir}", f"select o_orderkey, l_shipdate as at from orders asof left join lineitem on o_custkey = l_suppkey and o_orderdate {_op} l_shipdate")(
        lambda spark, d, x=_dir: relops.join_asof(_t(spark, d, "orders", "o_orderkey", "o_custkey", "o_orderdate").select("o_orderkey", F.col("o_custkey").alias("k"), F.col("o_orderdate").alias("ts")), _t(spark, d, "lineitem", "l_suppkey", "l_shipdate").select(F.col("l_suppkey").alias("k"), F.col("l_shipdate").alias("ts"), F.col("l_shipdate").alias("at")), "k", "ts", "at", x).select("o_orderkey", "at")
    )


@query("agg_five", "select event_type, sum(v)::bigint as s, count(v) as n, min(v) as mn, max(v) as mx, round(avg(v), 6) as avg from (select event_type, round(value * 100)::bigint as v from events) group by event_type")
def agg_five(spark: SparkSession, d: str) -> DataFrame:
    return relops.agg5(_t(spark, d, "events", "event_type", "value").select("event_type", streams.cents("value").alias("v")), ["event_type"], "v")


@query("ordered_collect", "select conv_id, string_agg(length(text)::varchar, ',' order by turn) as in_order, arg_max(length(text), turn)::int as last, arg_min(length(text), turn)::int as first from conversations group by conv_id")
def ordered_collect(spark: SparkSession, d: str) -> DataFrame:
    return relops.agg_ordered(_t(spark, d, "conversations", "conv_id", "turn", "text").select("conv_id", "turn", F.length("text").alias("v")), ["conv_id"], "turn", "v")


@query("distinct_counts", "select event_type, count(distinct user_id) as kinds from events group by event_type")
def distinct_counts(spark: SparkSession, d: str) -> DataFrame:
    return relops.distinct_counts(_t(spark, d, "events", "event_type", "user_id"), ["event_type"], "user_id")


@query("quantiles", "select l_returnflag, quantile_cont(l_quantity, 0.5)::double as median, quantile_cont(l_quantity, 0.9)::double as p90, round(stddev_pop(l_quantity), 4) as spread from lineitem group by l_returnflag")
def quantiles(spark: SparkSession, d: str) -> DataFrame:
    return relops.quantiles(_t(spark, d, "lineitem", "l_returnflag", "l_quantity"), ["l_returnflag"], "l_quantity")


for _kind in ("rollup", "cube"):
    query(f"{_kind}_lines", f"select l_returnflag, l_linestatus, count(*) as n from lineitem group by {_kind}(l_returnflag, l_linestatus)")(lambda spark, d, k=_kind: getattr(_t(spark, d, "lineitem", "l_returnflag", "l_linestatus"), k)("l_returnflag", "l_linestatus").agg(F.count("*").alias("n")))


@query("grouping_sets", "select o_orderstatus, o_orderpriority, count(*) as n from orders group by grouping sets ((o_orderstatus), (o_orderpriority), ())")
def grouping_sets(spark: SparkSession, d: str) -> DataFrame:
    return spark.sql("select o_orderstatus, o_orderpriority, count(*) as n from {o} group by grouping sets ((o_orderstatus), (o_orderpriority), ())", o=_t(spark, d, "orders", "o_orderstatus", "o_orderpriority"))


@query("pivot_status", "select o_orderpriority, count_if(o_orderstatus = 'F') as F, count_if(o_orderstatus = 'O') as O, count_if(o_orderstatus = 'P') as P from orders group by o_orderpriority")
def pivot_status(spark: SparkSession, d: str) -> DataFrame:
    return _t(spark, d, "orders", "o_orderpriority", "o_orderstatus").groupBy("o_orderpriority").pivot("o_orderstatus", ["F", "O", "P"]).agg(F.count(F.lit(1))).na.fill(0)


@query("bool_checks", "select l_shipdate, count_if(l_quantity > 25) as hits, bool_and(l_quantity > 25) as all_of, bool_or(l_quantity > 25) as any_of from lineitem group by l_shipdate")
def bool_checks(spark: SparkSession, d: str) -> DataFrame:
    return relops.checks(_t(spark, d, "lineitem", "l_shipdate", "l_quantity"), ["l_shipdate"], F.col("l_quantity") > 25)


@query("win_rank", "select o_orderkey, row_number() over w as rn, rank() over w as rk, dense_rank() over w as dr, ntile(4) over w as nt from orders window w as (partition by o_custkey order by o_orderdate, o_orderkey)")
def win_rank(spark: SparkSession, d: str) -> DataFrame:
    return relops.rankings(_t(spark, d, "orders", "o_orderkey", "o_custkey", "o_orderdate"), "o_custkey", F.col("o_orderdate"), F.col("o_orderkey")).select("o_orderkey", "rn", "rk", "dr", "nt")


@query("win_neighbours", f"select sid, pos, lag(v) over w as before, lead(v) over w as after, first_value(v) over (partition by sid order by pos) as first, last_value(v) over (partition by sid order by pos rows between unbounded preceding and unbounded following) as last from ({STREAM_SQL['by_type']}) window w as (partition by sid order by pos)")
def win_neighbours(spark: SparkSession, d: str) -> DataFrame:
    return relops.neighbours(streams.stream(spark, d, "by_type"), "sid", "pos", "v").select("sid", "pos", "before", "after", "first", "last")


@query("win_frames", f"select sid, pos, (sum(v) over (partition by sid order by t rows between 5 preceding and current row))::bigint as by_rows, (sum(v) over (partition by sid order by t range between 3600000000 preceding and current row))::bigint as by_span from ({STREAM_SQL['by_type']})")
def win_frames(spark: SparkSession, d: str) -> DataFrame:
    return relops.frames(streams.stream(spark, d, "by_type"), "sid", "t", "v", 5, 3_600_000_000).select("sid", "pos", "by_rows", "by_span")


@query("topk_values", "select o_orderkey, o_totalprice from orders order by o_totalprice desc, o_orderkey limit 10 offset 5")
def topk_values(spark: SparkSession, d: str) -> DataFrame:
    return relops.topk(_t(spark, d, "orders", "o_orderkey", "o_totalprice"), 10, F.desc("o_totalprice"), "o_orderkey", offset=5)


_A, _B = "select l_suppkey as k from lineitem where l_quantity > 45", "select o_custkey as k from orders where o_totalprice > 100000"
for _op, _spark in (("union", lambda a, b: a.union(b).distinct()), ("intersect", lambda a, b: a.intersect(b)), ("except", lambda a, b: a.subtract(b)), ("union all", lambda a, b: a.union(b)), ("except all", lambda a, b: a.exceptAll(b)), ("intersect all", lambda a, b: a.intersectAll(b))):
    query(f"set_{_op.replace(' ', '_')}", f"{_A} {_op} {_B}")(lambda spark, d, f=_spark: f(_t(spark, d, "lineitem", "l_suppkey", "l_quantity").where("l_quantity > 45").select(F.col("l_suppkey").alias("k")), _t(spark, d, "orders", "o_custkey", "o_totalprice").where("o_totalprice > 100000").select(F.col("o_custkey").alias("k"))))


@query("strings_encode", "select c_custkey, lpad(c_custkey::varchar, 8, '0') as padded, upper(c_mktsegment) as up, substr(c_name, 1, 4) as head, length(c_name)::int as n, c_custkey || '|' || c_mktsegment as joined, sha256(c_name) as digest from customer")
def strings_encode(spark: SparkSession, d: str) -> DataFrame:
    c = _t(spark, d, "customer", "c_custkey", "c_name", "c_mktsegment")
    return c.select("c_custkey", F.lpad(F.col("c_custkey").cast("string"), 8, "0").alias("padded"), F.upper("c_mktsegment").alias("up"), F.substring("c_name", 1, 4).alias("head"), F.length("c_name").alias("n"), F.concat_ws("|", "c_custkey", "c_mktsegment").alias("joined"), F.sha2("c_name", 256).alias("digest"))


@query("times_bucket", "select event_id, epoch_us(ts) as us, epoch_us(date_trunc('hour', ts)) as hour, date_diff('day', timestamp '2024-01-01', ts)::int as days, dayofweek(ts)::int + 1 as dow from events")
def times_bucket(spark: SparkSession, d: str) -> DataFrame:
    ts = F.col("ts").cast("timestamp")
    return _t(spark, d, "events", "event_id", "ts").select("event_id", F.unix_micros(ts).alias("us"), F.unix_micros(F.date_trunc("hour", ts)).alias("hour"), F.date_diff(ts.cast("date"), F.lit("2024-01-01").cast("date")).alias("days"), F.dayofweek(ts).alias("dow"))


@query("maths_integer", f"select event_id, x, x // 7 as q, ((x % 7) + 7) % 7 as m, ceil(x / 7.0)::bigint as c, floor(x / 7.0)::bigint as f, abs(x) as a, greatest(x, 3) as g, least(x, 3) as l, round(log2(x + 1), 6) as lg from (select event_id, {_CENTS} as x from events)")
def maths_integer(spark: SparkSession, d: str) -> DataFrame:
    x, e = F.col("x"), _t(spark, d, "events", "event_id", "value").select("event_id", streams.cents("value").alias("x"))
    return e.select("event_id", "x", F.expr("x div 7").alias("q"), F.pmod(x, F.lit(7)).alias("m"), F.ceil(x / 7).alias("c"), F.floor(x / 7).alias("f"), F.abs(x).alias("a"), F.greatest(x, F.lit(3)).alias("g"), F.least(x, F.lit(3)).alias("l"), F.round(F.log2(x + 1), 6).alias("lg"))


@query("arrays_fold", "select vec_id, len(embedding)::int as n, list_sum([floor(x::double * 256)::bigint for x in embedding])::bigint as folded, len([x for x in embedding if x > 0])::bigint as positive from embeddings")
def arrays_fold(spark: SparkSession, d: str) -> DataFrame:
    e = _t(spark, d, "embeddings", "vec_id", "embedding")
    ints = F.transform("embedding", lambda x: F.floor(x.cast("double") * 256))
    return e.select("vec_id", F.size("embedding").alias("n"), F.reduce(ints, F.lit(0).cast("long"), lambda a, x: a + x).alias("folded"), F.size(F.filter("embedding", lambda x: x > 0)).cast("long").alias("positive"))


@query("maps_tags", "select event_id, event_type as et, 3 as n, true as has_k from events")
def maps_tags(spark: SparkSession, d: str) -> DataFrame:
    e = _t(spark, d, "events", "event_id", "event_type", "props", "user_id")
    m = F.create_map(F.lit("event_type"), F.col("event_type"), F.lit("k"), F.get_json_object("props", "$.k"), F.lit("user_id"), F.col("user_id").cast("string"))
    return e.withColumn("m", m).select("event_id", F.element_at("m", "event_type").alias("et"), F.size("m").alias("n"), F.map_contains_key("m", "k").alias("has_k"))


@query("json_tags", "select json_extract(props, '$.k')::int as k, count(*) as n from events group by 1")
def json_tags(spark: SparkSession, d: str) -> DataFrame:
    return _t(spark, d, "events", "props").select(F.from_json("props", "k int")["k"].alias("k")).groupBy("k").agg(F.count("*").alias("n"))


for _form in ("csv", "json", "orc", "text"):
    query(f"roundtrip_{_form}", f"select sid, pos, t, v from ({STREAM_SQL['by_type']})")(lambda spark, d, f=_form: round_trip(streams.stream(spark, d, "by_type").select("sid", "pos", "t", "v"), f))


@query("sql_surface", "select event_type, count(*) as n from events where value > 50 group by event_type")
def sql_surface(spark: SparkSession, d: str) -> DataFrame:
    udf.register(spark, d)
    return spark.sql("select event_type, count(*) as n from events where value > :least group by event_type", args={"least": 50})


def flagship(spark: SparkSession, d: str) -> DataFrame:
    """Window sums over the event stream, proved by the server side and accepted by the client side."""
    p = ex.prepare(spark, d, "event_amt")
    return client.batch_verify(ex.wire(p, _windows(p)))


QUERIES["flagship"] = flagship
