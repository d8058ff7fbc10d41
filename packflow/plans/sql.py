"""DuckDB text for corpora, sizes and packing: the oracles' building blocks."""

from __future__ import annotations

from packflow.config import PackPolicy
from packflow.sources.corpora import lognormal_shares

CATALOG = "select l.l_orderkey, l.l_linenumber, l.l_partkey, l.l_suppkey, p.p_brand, concat_ws(' ', p_name, p_brand, p_type, p_size, l_orderkey, l_linenumber) as text from lineitem l join part p on l_partkey = p_partkey"
ORDER = "l_orderkey, l_linenumber, l_partkey, l_suppkey"


def _catalog(key: str, source: str = CATALOG) -> str:
    return f"select part_key, row_number() over (partition by part_key order by {ORDER}) as seq, text from (select {key} as part_key, * from ({source}))"


CORPORA = {
    "brand_nation": _catalog("p_brand || chr(31) || s_nationkey", f"select c.*, s.s_nationkey from ({CATALOG}) c join supplier s on l_suppkey = s_suppkey"),
    "supplier": _catalog("l_suppkey::varchar"),
    "part": _catalog("l_partkey::varchar"),
    "lang_source": "select lang || chr(31) || source as part_key, doc_id as seq, text from documents",
    "lang": "select lang as part_key, doc_id as seq, text from documents",
    "source": "select source as part_key, doc_id as seq, text from documents",
    "host": "select regexp_extract(url, '^[a-z]+://([^/:?#]+)', 1) as part_key, page_id as seq, regexp_replace(html, '<[^>]*>', ' ', 'g') as text from pages",
    "conversation": "select conv_id::varchar as part_key, turn as seq, concat_ws(': ', role, text) as text from conversations",
    "user_day": "select user_id || chr(31) || strftime(ts, '%Y-%m-%d') as part_key, event_id as seq, concat_ws(' ', event_type, user_id, props) as text from events",
    "user": "select user_id::varchar as part_key, event_id as seq, concat_ws(' ', event_type, user_id, props) as text from events",
    "event_type": "select event_type as part_key, event_id as seq, concat_ws(' ', event_type, user_id, props) as text from events",
    "customer": "select o_custkey::varchar as part_key, o_orderkey as seq, concat_ws(' ', o_orderpriority, o_orderstatus, o_orderkey) as text from orders",
}


def sizes(corpus: str) -> str:
    return f"select part_key, count(*)::bigint as n_texts, coalesce(sum(strlen(text)), 0)::bigint as n_bytes from ({CORPORA[corpus]}) group by part_key"


def arrival(source: str, order: str = "part_key") -> str:
    """A size table with its order of arrival; binary collation, nulls first as in Spark."""
    return f"select *, row_number() over (order by {order} nulls first)::bigint as arrival from ({source})"


def synthetic(parts: int, sigma: float, texts: str = "(select count(*) from lineitem)") -> str:
    """The synthetic size table: the same shares, floors and remainders."""
    values = ", ".join(f"({k}, {share!r}::double)" for k, share in enumerate(lognormal_shares(parts, sigma), 1))
    return f"""select 'k' || lpad(k::varchar, 5, '0') as part_key, n_texts, n_texts * 51 as n_bytes from (
        select k, (1 + floor(raw) + case when row_number() over (order by floor(raw) - raw, k) <= {texts} - sum(1 + floor(raw)) over () then 1 else 0 end)::bigint as n_texts
        from (select k, share * ({texts} - {parts}) as raw from (values {values}) v(k, share)))"""


def units(source: str, b_max: str, oversize: str) -> str:
    if oversize == "own":
        return f"select *, 0 as chunk, n_texts as n, n_texts as whole from ({source})"
    return f"select s.*, u.chunk::integer as chunk, least({b_max}, n_texts - u.chunk * {b_max})::bigint as n, n_texts as whole from ({source}) s, unnest(range(0, greatest(1, ceil(n_texts::double / {b_max})::bigint))) u(chunk)"


def greedy(source: str, b_min: str, b_max: str, ceiling: str = "before", oversize: str = "split", by: str = "0") -> str:
    """The plan of each lane (``by``) by a recursive walk over its units in arrival order.

    ``b_min`` and ``b_max`` are numbers or columns of ``source``.
    """
    over = f"u.b_total + n.n > n.b_max and u.b_total > 0" if ceiling == "before" else "false"
    total = f"case when {over} then n.n else u.b_total + n.n end"
    return f"""(with recursive un as (
        select *, row_number() over (partition by lane order by arrival, part_key, chunk) as pos
        from (select {by} as lane, part_key, arrival, chunk, n, whole, {b_min} as b_min, {b_max} as b_max from ({units(source, b_max, oversize)}))
    ), walk as (
        select n.lane, n.pos, 0::bigint as pack_id, n.n as total, case when n.n >= n.b_min then 0 else n.n end as b_total,
            case when n.n >= n.b_min then 1 else 0 end as closes, false as cut
        from un n where n.pos = 1
        union all
        select n.lane, n.pos, u.pack_id + case when u.closes = 1 or ({over}) then 1 else 0 end, {total},
            case when {total} >= n.b_min then 0 else {total} end, case when {total} >= n.b_min then 1 else 0 end, {over}
        from walk u join un n on n.lane = u.lane and n.pos = u.pos + 1
    ), joined as (
        select w.*, n.part_key, n.arrival, n.chunk, n.n, n.whole, n.b_min, n.b_max,
            lead(w.cut) over (partition by w.lane order by w.pos) as next_cut
        from walk w join un n on n.lane = w.lane and n.pos = w.pos
    )
    select lane, pack_id, part_key, chunk, n, arrival, whole, max(reason) over (partition by lane, pack_id) as reason,
        (sum(n) over (partition by lane, pack_id order by pos) - n)::bigint as start_off, (sum(n) over (partition by lane, pack_id order by pos))::bigint as end_off
    from (select *, case when closes = 1 and whole > b_max then 'oversize' when closes = 1 and total >= b_max then 'ceiling' when closes = 1 then 'efficiency'
            when next_cut then 'ceiling' when next_cut is null then 'final' end as reason from joined))"""


def fit_decreasing(source: str, capacity: str, best: bool = False) -> str:
    """First or best fit of sizes in descending order, by a recursive walk with the bins' loads in a list."""
    fits = "[case when x + n <= cap then x else -1 end for x in loads]"
    place = f"case when list_max({fits}) < 0 then null else list_position({fits}, list_max({fits})) end" if best else "nullif(list_position([x + n <= cap for x in loads], true), 0)"
    return f"""(with recursive s as (
        select part_key, n_texts, {capacity} as cap, row_number() over (order by n_texts desc, part_key) as pos from ({source})
    ), walk as (
        select pos, part_key, n_texts as n, 1::bigint as bin, [n_texts]::bigint[] as loads from s where pos = 1
        union all
        select pos, part_key, n, bin, case when bin > len(loads) then list_append(loads, n) else list_concat(list_append(loads[1:bin - 1], loads[bin] + n), loads[bin + 1:]) end
        from (select pos, part_key, n, loads, coalesce({place}, len(loads) + 1)::bigint as bin
              from (select s.pos, s.part_key, s.n_texts as n, s.cap, w.loads from walk w join s on s.pos = w.pos + 1))
    )
    select part_key, n, bin - 1 as pack_id from walk)"""


def totals(plan: str) -> str:
    return f"select lane, pack_id, count(*)::bigint as parts, sum(n)::bigint as n, max(reason) as reason from {plan} p group by lane, pack_id"


def policy(source: str, p: PackPolicy) -> str:
    return greedy(source, str(p.b_min), str(p.b_max), p.ceiling, p.oversize)


def stats(source: str) -> str:
    return f"""select count(*)::bigint as parts, sum(n_texts)::bigint as texts, min(n_texts) as n_min, max(n_texts) as n_max, avg(n_texts) as mean,
        stddev_pop(n_texts) as sd, median(n_texts) as median, stddev_pop(n_texts) / avg(n_texts) as cv, stddev_pop(n_texts) / median(n_texts) as std_over_median from ({source})"""


def checksums(corpus: str, dim: int, keys: str = "part_key, seq") -> str:
    """The hash encoder's integer checksums of every text."""
    return f"""select {keys}, sum(v * (bucket + 1))::bigint as weighted, sum(v * v)::bigint as squares, count(*) filter (v <> 0)::bigint as touched from (
        select {keys}, ('0x' || substr(h, 1, 7))::bigint % {dim} as bucket, sum(1 - 2 * (('0x' || substr(h, 8, 1))::bigint % 2)) as v
        from (select {keys}, md5(unnest(string_split(text, ' '))) as h from ({CORPORA.get(corpus, corpus)})) group by all) group by {keys}"""
