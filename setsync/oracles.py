"""DuckDB twins of the catalogue's queries: set algebra for results, per-element arithmetic for traces."""

from __future__ import annotations

from setsync.operators.cells import hit_rates

COST = 259.2
LN2 = "0.6931471805599453"


def h(text: str) -> str:
    """The first 60 bits of md5 of a text expression."""
    return f"(('0x' || substr(md5({text}), 1, 15))::BIGINT)"


def field(x: str) -> str:
    return f"case when {x} is null then '~' else length({x}::varchar) || '=' || {x}::varchar end"


def xor_bit(pos: str) -> str:
    return f"(case when {pos} % 64 = 63 then (-9223372036854775807 - 1) else (1::BIGINT << ({pos} % 64)::INT) end)"


def base(points: list[float], n: str = "least(100000, (select count(*) from lineitem) // 3)", trials: int = 1, keys: str | None = None) -> str:
    """CTEs ``e(run_id, side, digest, payload_bytes)`` of a sweep (over lineitem, or the digests of ``keys``) and ``runs``."""
    key = " || ';' || ".join(field(x) for x in ("l_orderkey", "l_partkey", "l_suppkey", "l_linenumber", "epoch_us(l_shipdate)"))
    values = ", ".join(f"('{p:g}/{t}', {p}::DOUBLE, {t})" for p in points for t in range(trials))
    return f"""
    keys as ({keys or f"select distinct {h(key)} digest from lineitem"}),
    el as (select digest, trial, (8 + {h("digest || ':91'")} % 73)::INT payload_bytes, row_number() over (partition by trial order by {h("digest || ':31:' || trial")}, digest) - 1 as rank from keys, range({trials}) t(trial)),
    runs as (select run_id, pct similarity_pct, trial, n, floor(n * (1 - pct / 100) / (1 + pct / 100) + 0.5)::BIGINT u
             from (values {values}) v(run_id, pct, trial), (select ({n})::BIGINT n) s),
    e as (select run_id, -1 side, digest, payload_bytes from el join runs using (trial) where rank < n
          union all select run_id, 1, digest, payload_bytes from el join runs using (trial) where rank < n - u or (rank >= n and rank < n + u))"""


SIZES = """
    per as (select run_id, digest, min(side) low, max(side) high, max(payload_bytes) b from e group by 1, 2),
    sizes as (select run_id, count(*) filter (where low < 0) n_a, count(*) filter (where high > 0) n_b,
              count(*) filter (where high < 0) a_only, count(*) filter (where low > 0) b_only, count(*) filter (where low < 0 and high > 0) common,
              coalesce(sum(b) filter (where high < 0), 0)::BIGINT a_only_bytes, coalesce(sum(b) filter (where low > 0), 0)::BIGINT b_only_bytes,
              coalesce(sum(b) filter (where low < 0 and high > 0), 0)::BIGINT common_bytes,
              a_only + b_only d, common / (a_only + b_only + common) jaccard from per group by 1)"""

DIFFERENCE = "select run_id, digest, side::INT side from (select run_id, digest, sum(side) side from e group by 1, 2) where side <> 0"


def phase(number: int, source: str, receiver: str, slices: int) -> str:
    """CTEs m{k}, bits{k}, miss{k}(run_id, digest, first_miss), hist{k}, stop{k}."""
    k = number
    pos = h(f"digest || ':{k}:' || slice") + " % m"
    return f"""
    m{k} as (select run_id, count(*) n, ceil(count(*) / {LN2})::BIGINT m from {source} group by 1),
    bits{k} as (select distinct run_id, slice, {pos} pos from {source} join m{k} using (run_id), range({slices}) t(slice)),
    seen{k} as (select run_id, digest, slice, {pos} pos from {receiver} join m{k} using (run_id), range({slices}) t(slice)),
    miss{k} as (select r.run_id, r.digest, case when any_value(m.m) is null then -1 else min(x.slice) end first_miss
               from {receiver} r left join m{k} m using (run_id)
               left join (select * from seen{k} anti join bits{k} using (run_id, slice, pos)) x on x.run_id = r.run_id and x.digest = r.digest group by 1, 2),
    new{k} as (select run_id, first_miss slice, count(*) c from miss{k} where first_miss >= 0 group by 1, 2),
    hist{k} as (select m{k}.run_id, slice::INT slice, m, coalesce(c, 0) new_rejects,
               (sum(coalesce(c, 0)) over (partition by m{k}.run_id order by slice))::BIGINT cum_rejects, m * (slice + 1) cum_bits
               from m{k} cross join range({slices}) t(slice) left join new{k} using (run_id, slice)),
    stop{k} as (select run_id, max(m) m, (min(slice) filter (where new_rejects * 2592 < m * 10))::INT stop,
               arg_min(new_rejects, slice) filter (where new_rejects * 2592 < m * 10) new_at_stop from hist{k} group by 1)"""


def one(points: list[float], slices: int = 13, **k) -> str:
    return f"with {base(points, **k)}, l as (select * from e where side < 0), r as (select * from e where side > 0), {phase(1, 'l', 'r', slices)}"


def both(points: list[float], **k) -> str:
    sus = "s as (select run_id, digest from miss1 left join stop1 using (run_id) where not (first_miss is not null and (first_miss < 0 or first_miss <= stop)))"
    return f"{one(points, **k)}, {sus}, {phase(2, 's', 'l', 24)}"


#: What both phases let through, and the charged hybrid (both over ``both``).
LEAKS = """s2 as (select run_id, digest from miss2 left join stop2 using (run_id) where not (first_miss is not null and (first_miss < 0 or first_miss <= stop))),
    lk as (select run_id, count(*) leaks from (select run_id, digest from (select * from s union all select * from s2) group by 1, 2 having count(*) = 1) group by 1)"""
HYBRID = f"""{LEAKS}, hyb as (select stop1.run_id, stop1.stop + 1 slices_1, ((stop1.stop + 1) * ceil(stop1.m / 8))::BIGINT bytes_1, coalesce(stop2.stop + 1, 0) slices_2, coalesce((stop2.stop + 1) * ceil(stop2.m / 8), 0)::BIGINT bytes_2, coalesce(leaks, 0) leaks,
    round(bytes_1 + bytes_2 + coalesce(leaks, 0) * {COST}::DOUBLE / 8, 3) metadata_bytes from stop1 left join stop2 using (run_id) left join lk using (run_id))"""


def charged(points: list[float], methods: list[str], rates: list[float] = [], **k) -> str:
    """CTE ``x`` of the measures of charged methods."""
    formulas = {"cell_stream": "ceil(d * 1.35::DOUBLE) * 24", "syndrome_sketch": "8 * d", "digest_exchange": "8 * n_a", "full_transfer": "common_bytes"}
    parts = [f"select run_id, '{m}' \"method\", ({formulas[m]})::DOUBLE metadata_bytes from sizes" for m in methods if m in formulas]
    parts.append("select run_id, 'sliced_hybrid', metadata_bytes from hyb")
    if rates:
        parts.append("select run_id, 'static_' || (eps * 100)::INT, (ceil(bits_1 / 8) + ceil(bits_2 / 8) + ceil(leaks * 1.35::DOUBLE) * 24)::DOUBLE from counts")
    parts[0] = parts[0].replace("'sliced_hybrid',", "'sliced_hybrid' \"method\",")
    return f"""{both(points, **k)}, {SIZES}, {HYBRID}, {filter_ctes(rates) + ',' if rates else ''} m as ({' union all '.join(parts)}),
        x as (select "method", run_id, similarity_pct, trial, d, metadata_bytes, round(metadata_bytes + a_only_bytes + b_only_bytes, 3) total_bytes, a_only_bytes + b_only_bytes minimum_bytes,
              case when a_only_bytes + b_only_bytes > 0 then round(round(metadata_bytes + a_only_bytes + b_only_bytes, 3) / (a_only_bytes + b_only_bytes), 6) end overhead_ratio from m join sizes using (run_id) join runs using (run_id))"""


def crossing(a: str, b: str) -> str:
    return f"""select '{a}' "method", '{b}' other, max(similarity_pct) crossover_similarity from
        (select p.similarity_pct, min(p.similarity_pct) filter (where p.total_bytes > q.total_bytes) over () w from (select * from x where "method" = '{a}') p join (select * from x where "method" = '{b}') q using (similarity_pct))
        where w is null or similarity_pct < w"""


def filter_ctes(rates: list[float]) -> str:
    """Static filters of every rate both ways: p1 (right side), p2 (left side) with what passes, and ``counts``. An element's hashes serve all rates."""
    values = ", ".join(f"({r}::DOUBLE)" for r in rates)

    def sized(name: str, source: str) -> str:
        return f"""{name} as (select run_id, eps, count(*) n, ceil(-count(*) * ln(eps) / ({LN2} * {LN2}))::BIGINT m, greatest(1, round(-ln(eps) / {LN2})::INT) k
                   from {source} group by run_id, eps)"""

    def probe(name: str, size: str, source: str, receiver: str, p: int) -> str:
        return f"""{name}_hash as (select digest, hash, {h(f"digest || ':{500 + p}:' || hash")} v from (select distinct digest from e), range(8) t(hash)),
            {name}_bits as (select distinct run_id, eps, v % m pos from {source} join {size} using (run_id, eps) join {name}_hash using (digest) where hash < k),
            {name}_seen as (select run_id, eps, digest, v % m pos from {receiver} join {size} using (run_id, eps) join {name}_hash using (digest) where hash < k),
            {name} as (select run_id, eps, digest, min((b.pos is not null)::INT) = 1 passes from {name}_seen left join {name}_bits b using (run_id, eps, pos) group by 1, 2, 3)"""

    return f"""rates as (select eps from (values {values}) v(eps)),
        fl as (select run_id, eps, digest from e, rates where side < 0), fr as (select run_id, eps, digest from e, rates where side > 0),
        {sized('f1', 'fl')}, {probe('p1', 'f1', 'fl', 'fr', 1)},
        q as (select run_id, eps, digest from p1 where passes), {sized('f2', 'q')}, {probe('p2', 'f2', 'q', 'fl', 2)},
        leak as (select run_id, eps, digest, sum(s) s from (select run_id, eps, digest, 1 s from q union all select run_id, eps, digest, -1 from p2 where passes) group by 1, 2, 3 having sum(s) <> 0),
        leaks as (select run_id, eps, count(*) leaks, count(*) filter (where s < 0) wanted from leak group by 1, 2),
        counts as (select f1.run_id, f1.eps, f1.m bits_1, coalesce(f2.m, 0) bits_2, coalesce(leaks.leaks, 0) leaks, coalesce(wanted, 0) wanted
                   from f1 left join f2 using (run_id, eps) left join leaks using (run_id, eps))"""


def filters(points: list[float], rates: list[float]) -> str:
    return f"with {base(points)}, {filter_ctes(rates)}"


def chain(source: str, cells: int) -> str:
    """Recursive CTE ``spots(run_id, side, digest, cell)`` of all cells below ``cells``."""
    u = h("digest || ':77:' || (step + 1)") + " / 1152921504606846976.0::DOUBLE"
    return f"""spots as (
        select run_id, side, digest, 0::BIGINT cell, 0 step from {source}
        union all
        select run_id, side, digest, nxt, step + 1 from (
          select run_id, side, digest, step, cell + greatest(1, ceil((cell::DOUBLE + 1.5::DOUBLE) * (1::DOUBLE / sqrt(1::DOUBLE - {u}) - 1::DOUBLE))::BIGINT) nxt from spots)
        where nxt < {cells})"""


def sums(extra: str = "") -> str:
    chk = h("digest || ':1000003'")
    return f"bit_xor(digest) id_xor, bit_xor({chk}) check_xor"


def ledger(parts: dict[str, list[tuple[str, bool, bool, str]]]) -> str:
    """CTE ``summary`` of methods: each has (bytes, metadata, core, messages) lines over ``sizes``."""
    rows = []
    for method, entries in parts.items():
        meta = " + ".join(["0"] + [b for b, m, _, _ in entries if m])
        core = " + ".join(["0"] + [b for b, m, c, _ in entries if m and c])
        rest = " + ".join(["0"] + [b for b, m, _, _ in entries if not m])
        some = " or ".join(f"({n}) > 0" for _, _, _, n in entries)
        rows.append(f"select run_id, '{method}' \"method\", ({meta})::DOUBLE metadata_bytes, ({core})::DOUBLE metadata_core_bytes, ({rest})::DOUBLE payload_sent, ({meta} + {rest})::DOUBLE total_bytes from sizes where {some}")
    return "summary as (" + " union all ".join(rows) + ")"


PAYLOAD = [("a_only_bytes", False, False, "a_only"), ("b_only_bytes", False, False, "b_only")]
FULL = {"full_transfer": [*PAYLOAD, ("common_bytes", True, True, "common")]}
DIGESTS = {"digest_exchange": [("8 * n_a", True, True, "n_a"), ("8 * a_only", True, False, "a_only"), *PAYLOAD]}
SKETCH = {"syndrome_sketch": [("8 * d", True, True, "d"), ("8 * a_only", True, False, "a_only"), *PAYLOAD]}


def lagging(extra: str) -> str:
    cuts = ["2024-01-10", "2024-01-20", "2024-01-29"]
    rows = " union all ".join(f"select 'before {c}' run_id, count(*) filter (where ts < TIMESTAMP '{c}') a, count(*) b from (select distinct event_id, ts from events)" for c in cuts)
    return f"with x as ({rows}) {extra}"


def semijoin_rows(on: str = "k") -> str:
    row = " || ';' || ".join(field(x) for x in ("k", "l_linenumber", "l_partkey", "l_suppkey"))
    return f"""with lines as (select l_orderkey k, l_linenumber, l_partkey, l_suppkey from lineitem), urgent as (select o_orderkey k from orders where o_orderpriority = '1-URGENT'),
        w as (select *, length({row}) b from lines)"""


def filter_semijoin_sql() -> str:
    parts = []
    for i, eps in enumerate((0.01, 0.25)):
        pos = lambda d: h(f"{d} || ':501:' || hash") + " % m"
        parts.append(f"""f{i} as (select ceil(-count(*) * ln({eps}::DOUBLE) / ({LN2} * {LN2}))::BIGINT m, greatest(1, round(-ln({eps}::DOUBLE) / {LN2})::INT) k from src),
            b{i} as (select distinct {pos('digest')} pos from src, f{i}, lateral (select unnest(range(f{i}.k)) hash)),
            t{i} as (select digest, min((b.pos is not null)::INT) ok from (select digest, {pos('digest')} pos from (select distinct {h('k::varchar')} digest from lines), f{i}, lateral (select unnest(range(f{i}.k)) hash)) x left join b{i} b using (pos) group by 1),
            o{i} as (select 'filter_semijoin_{eps:g}' "method", ceil(any_value(m) / 8)::DOUBLE sent_bytes, count(b) rows_shipped, coalesce(sum(b), 0)::BIGINT row_bytes
                   from f{i}, (select w.b from w join t{i} on t{i}.digest = {h('w.k::varchar')} where ok = 1))""")
    union = " union all ".join(f"select *, sent_bytes + row_bytes total_bytes from o{i}" for i in range(2))
    return f"{semijoin_rows()}, src as (select distinct {h('k::varchar')} digest from urgent), {', '.join(parts)} {union}"


def sliced_trace_sql() -> str:
    pos = lambda d: h(f"{d} || ':1:' || slice") + " % m"
    return f"""{semijoin_rows()}, src as (select distinct {h('k::varchar')} digest from urgent), cost as (select round(80 * avg(b)) tenths from w),
        m as (select ceil(count(*) / {LN2})::BIGINT m from src), keys as (select {h('k::varchar')} digest, count(*) c from lines group by k),
        bits as (select distinct slice, {pos('digest')} pos from src, m, range(40) t(slice)),
        miss as (select digest, any_value(c) c, min(slice) first_miss from (select digest, c, slice, {pos('digest')} pos from keys, m, range(40) t(slice)) x anti join bits using (slice, pos) group by 1),
        per as (select first_miss slice, sum(c) c from miss group by 1),
        hist as (select t.slice::INT slice, m, coalesce(c, 0)::BIGINT new_rejects, (sum(coalesce(c, 0)) over (order by t.slice))::BIGINT cum_rejects, m * (t.slice + 1) cum_bits
                 from m cross join range(40) t(slice) left join per on per.slice = t.slice),
        stopped as (select min(slice) stop from hist, cost where new_rejects * tenths < m * 10)
        select hist.*, stop from hist, stopped where slice <= stop"""


def join_traffic_sql() -> str:
    joins = {
        "orders of customers": ("select o_custkey k, o_orderkey from orders", "select c_custkey k from customer where c_mktsegment = 'BUILDING'", ("k", "o_orderkey")),
        "lines of parts": ("select l_partkey k, l_orderkey, l_linenumber, l_suppkey from lineitem", "select p_partkey k from part where p_size <= 10", ("k", "l_orderkey", "l_linenumber", "l_suppkey")),
    }
    parts = []
    for name, (rows, keys, columns) in joins.items():
        spelled = " || ';' || ".join(field(x) for x in columns)
        weighed = f"(select k, length({spelled}) b from ({rows}))"
        matched = f"(select * from {weighed} where k in (select k from ({keys})))"
        sent = f"(select 8 * count(distinct k) from ({keys}))::DOUBLE"
        parts.append(f"select '{name}' joined, 'ship_all' \"method\", 0::DOUBLE sent_bytes, count(*) rows_shipped, sum(b)::BIGINT row_bytes, sum(b)::DOUBLE total_bytes from {weighed}")
        parts.append(f"select '{name}', 'key_semijoin', {sent}, count(*), sum(b)::BIGINT, {sent} + sum(b) from {matched}")
    return " union all ".join(parts)


def all_sql() -> dict[str, str]:
    points, few, close = [0.0, 20.0, 50.0, 85.0, 95.0, 100.0], [50.0, 95.0], [95.0, 99.0]
    full = [float(s) for s in range(0, 101, 5)]
    high = [85 + 0.5 * k for k in range(31)]
    methods = ["sliced_hybrid", "cell_stream", "syndrome_sketch", "digest_exchange", "full_transfer"]
    pos1 = h("digest || ':1:' || slice") + " % m"
    left = f"with {base(few)}, m as (select run_id, ceil(count(*) / {LN2})::BIGINT m from e where side < 0 group by 1)"
    result = lambda p, **k: f"with {base(p, **k)} {DIFFERENCE}"
    spot = "h * 100 + " + h("digest || ':900:' || h") + " % 100"
    signs = "(1 - 2 * ((" + h("digest || ':700:' || (j // 48)") + " >> (j % 48)::INT) & 1))"
    rates = ", ".join(f"({i}, {float(r)!r}::DOUBLE)" for i, r in enumerate(hit_rates(64)) if i)
    grp, bin_ = h("digest || ':300'") + " % 200", h("digest || ':310:1'") + " % 127"
    kinds = " union all ".join(
        f"select '{m}' \"method\", {p} phase, '{k}' kind, ({b})::DOUBLE bytes, ({n})::BIGINT messages from sizes where ({n}) > 0"
        for m, p, k, b, n in (
            ("full_transfer", 1, "payload", "a_only_bytes", "a_only"), ("full_transfer", 1, "payload_common", "common_bytes", "common"), ("full_transfer", 1, "payload", "b_only_bytes", "b_only"),
            ("syndrome_sketch", 1, "sketch", "8 * d", "d"), ("syndrome_sketch", 1, "wanted_digests", "8 * a_only", "a_only"), ("syndrome_sketch", 9, "payload", "a_only_bytes", "a_only"), ("syndrome_sketch", 9, "payload", "b_only_bytes", "b_only"),
        )
    )
    measured = f"with {base(full)}, {SIZES}, {ledger(FULL | DIGESTS | SKETCH)}, x as (select \"method\", similarity_pct, d, total_bytes, a_only_bytes + b_only_bytes minimum_bytes from summary join sizes using (run_id) join runs using (run_id))"

    session = """with g as (select user_id, ts, case when ts - lag(ts) over (partition by user_id order by ts) < interval 1 hour then 0 else 1 end s from events),
        n as (select user_id, sum(s) over (partition by user_id order by ts rows unbounded preceding) k from g), c as (select user_id, k, count(*) n from n group by 1, 2)
        select count(*) sessions, sum(n)::BIGINT events, max(n) largest from c"""
    return {
        "replica_pair_sizes": f"with {base(points)}, {SIZES} select * from sizes",
        "jaccard_sweep": f"with {base(full)}, {SIZES} select similarity_pct, d, jaccard from sizes join runs using (run_id)",
        "exact_difference": f"with {base(few)} select run_id, digest, max(payload_bytes) payload_bytes, sum(side)::INT side from e group by 1, 2 having sum(side) <> 0",
        "slice_bits": f"{left} select run_id, slice::INT slice, m, pos // 64 word_no, bit_or({xor_bit('pos')}) bits from (select run_id, slice, m, {pos1} pos from e join m using (run_id), range(2) t(slice) where side < 0) group by 1, 2, 3, 4",
        "slice_fill": f"{left} select run_id, slice::INT slice, m, count(distinct pos) set_bits, round(count(distinct pos) / m, 6) fill from (select run_id, slice, m, {pos1} pos from e join m using (run_id), range(4) t(slice) where side < 0) group by 1, 2, 3",
        "phase1_histogram": f"{one(points)} select * from hist1",
        "phase1_stop": f"{one(points)} select * from stop1",
        "phase2_histogram": f"{both(points)} select * from hist2",
        "phase2_stop": f"{both(points)} select * from stop2",
        "hybrid_metadata": f"{both(points)}, {HYBRID} select * from hyb",
        "leak_cost_stops": one(points) + "".join(
            f" {'union all' if k else ''} select '{name}' cost, run_id, max(m) m, (min(slice) filter (where new_rejects * {round(bits * 10)} < m * 10))::INT stop, arg_min(new_rejects, slice) filter (where new_rejects * {round(bits * 10)} < m * 10) new_at_stop from hist1 group by run_id"
            for k, (name, bits) in enumerate((("cells, all fields", 259.2), ("cells, no count", 172.8), ("sketch", 64.0)))
        ),
        "effective_rates": f"{one(points)} select run_id, stop, pow(0.5::DOUBLE, stop + 1) effective_rate from stop1",
        "hybrid_turn_based": f"""{both(few)}, st as (select run_id, 1 phase, stop + 1 k, ceil(m / 8)::BIGINT b from stop1 union all select run_id, 2, stop + 1, ceil(m / 8)::BIGINT from stop2)
            select run_id, phase, 'turn_based' "mode", (2 * k)::BIGINT messages, k * b + k bytes from st union all select run_id, phase, 'continuous', k + 2, (k + 1) * b + 1 from st""",
        "hybrid_natural": "select unnest(['orders', 'part', 'documents', 'pages', 'conversations', 'embeddings']) run_id, true converged, 0 false_rejects",
        "stream_slices": f"{one([50.0])} select slice, new_rejects, m, stop, 9 - stop overshoot from hist1 join (select run_id, stop from stop1) using (run_id) where slice <= stop",
        "operation_counts": f"""{both(points)}, {LEAKS},
            spent as (select run_id, 'test_1' operation, sum(coalesce(least(first_miss, stop), stop, -1) + 1)::DOUBLE times from miss1 left join stop1 using (run_id) group by 1
              union all select run_id, 'test_2', sum(coalesce(least(first_miss, stop), stop, -1) + 1)::DOUBLE from miss2 left join stop2 using (run_id) group by 1
              union all select run_id, 'set_1', (n * (stop + 1))::DOUBLE from m1 join stop1 using (run_id) union all select run_id, 'set_2', (n * (stop + 1))::DOUBLE from m2 join stop2 using (run_id)
              union all select run_id, 'cell_update', round(n * (1 + 2 * ln(ceil(coalesce(leaks, 0) * 1.35::DOUBLE) / 2 + 1)), 3) from (select run_id, count(*) n from (select run_id from s union all select run_id from s2) group by 1) left join lk using (run_id)
              union all select run_id, 'peel', leaks::DOUBLE from lk)
            select * from spent""",
        "experiment_static": f"{charged(full, ['sliced_hybrid'], [0.01, 0.05, 0.1, 0.25])} select * from x",
        "experiment_charged": f"{charged(full, methods)} select * from x",
        "experiment_charged_high": f"{charged(high, methods)} select * from x",
        "savings": f"""{charged(full, methods)}, own as (select similarity_pct, metadata_bytes m, total_bytes t from x where "method" = 'sliced_hybrid'), rest as (select * from x join own using (similarity_pct) where "method" <> 'sliced_hybrid')
            select "method" other, similarity_pct, 'metadata_bytes' measure, round(case when metadata_bytes <> 0 then (metadata_bytes - m) / metadata_bytes * 100 end, 6) saving_pct from rest
            union all select "method", similarity_pct, 'total_bytes', round(case when total_bytes <> 0 then (total_bytes - t) / total_bytes * 100 end, 6) from rest""",
        "crossover_hybrid": f"{charged(sorted({*full, *high}), methods)} " + " union all ".join(crossing("sliced_hybrid", m) for m in methods[1:]),
        "trials_summary": f"""{charged([50.0, 90.0], ["sliced_hybrid", "full_transfer"], trials=30)} select "method", similarity_pct, avg(d) d, {", ".join(f"round(avg({c}), 4) {c}_mean, round(stddev_samp({c}), 4) {c}_sd" for c in ("metadata_bytes", "total_bytes", "overhead_ratio"))}, count(*) trials from x group by 1, 2""",
        "sketch_decode_result": result([85.0, 90.0, 95.0, 99.0], n="2000"),
        "routine_sync": result([99.5, 99.9, 100.0], n="(select count(distinct event_id) from events) * 9 // 10", keys=f"select distinct {h(field('event_id'))} digest from events"),
        "uneven_sets": """select 'copies' run_id, -1 side, count(distinct text) n from documents where text not in (select text from documents where doc_id % 3 <> 0)
            union all select 'unequal', 1, count(*) from orders where o_orderkey % 10 <> 0
            union all select 'disjoint', -1, count(distinct text) from documents where text not in (select text from benchmark) union all select 'disjoint', 1, count(distinct text) from benchmark where text not in (select text from documents)""",
        "semijoin_traffic": join_traffic_sql(),
        "worked_ranges_six": "select 'ranges' run_id, digest::BIGINT digest, side::INT side from (values (1, -1), (2, -1), (100002, 1), (100003, 1)) v(digest, side)",
        "hybrid_result": result(points),
        "hybrid_sharded": result(few),
        "converged_union": f"with {base(points)}, u as (select distinct run_id, digest from e) select run_id, side::INT side, count(*) n, sum(digest % 1000003)::BIGINT digest_sum from u, (values (-1), (1)) v(side) group by 1, 2",
        "static_filter_fpr": f"{filters([0.0, 50.0], [0.01, 0.25])} select run_id, eps, count(*) non_members, sum(passes::INT)::BIGINT passed from p1 anti join (select run_id, digest from e where side < 0) z using (run_id, digest) group by 1, 2",
        "static_hybrid_bytes": f"{filters(few, [0.01, 0.25])} select * from counts",
        "best_static_eps": f"{filters(few, [k / 200 for k in range(1, 101)])}, c as (select run_id, eps, (ceil(bits_1 / 8) + ceil(bits_2 / 8) + ceil(leaks * 1.35::DOUBLE) * 24)::DOUBLE metadata_bytes from counts) select run_id, eps, metadata_bytes from c qualify row_number() over (partition by run_id order by metadata_bytes, eps) = 1",
        "static_hybrid_result": result(few),
        "partitioned_equals_slices": f"{one(few, 3)} select run_id, count(*) tested, count(*) filter (where first_miss is null) passed from miss1 group by 1",
        "xortable_cells": f"with {base(close)} select run_id, side, cell, {sums()}, count(*) cnt from (select run_id, side, digest, ({spot})::BIGINT cell from e, range(3) t(h)) group by 1, 2, 3",
        "xortable_result": result(close),
        "cell_prefix": f"with recursive {base(close)}, {chain('e', 32)} select run_id, cell, {sums()}, sum(side)::BIGINT cnt from spots group by 1, 2",
        "cell_stream_result": result(close),
        "relational_peel_result": result([99.0]),
        "maintained_cells": f"with recursive {base([95.0])}, l as (select * from e where side < 0 and digest % 10 <> 0), {chain('l', 32)} select run_id, side, cell, {sums()}, count(*) cnt from spots group by 1, 2, 3",
        "syndrome_bytes": f"with {base(points)}, {SIZES}, {ledger(SKETCH)} select * from summary",
        "syndrome_result": result([98.0]),
        "parity_round1_bins": f"with {base(close)} select run_id, {grp} grp, {bin_} bin, bit_xor(digest) id_xor from e group by 1, 2, 3 having count(*) % 2 = 1",
        "parity_result": result(points),
        "sign_sum_estimate": f"with {base(points)}, y as (select run_id, j, sum({signs} * side)::BIGINT y from e, range(128) t(j) group by 1, 2) select run_id, sum(y * y) / 128.0::DOUBLE d_hat, ceil(sum(y * y) / 128.0::DOUBLE * 1.38::DOUBLE)::BIGINT d_safe from y group by 1",
        "cell_moment_estimate": f"""with recursive {base(few)}, {chain('e', 64)}, c as (select run_id, cell, sum(side) cnt from spots group by 1, 2), g as (select run_id, max(cnt) filter (where cell = 0) g from c group by 1), rates as (select * from (values {rates}) v(cell, rate))
            select run_id, round(sum((coalesce(cnt, 0) - coalesce(g, 0) * rate) ** 2) / sum(rate * (1 - rate)), 3) d_hat from g cross join rates left join c using (run_id, cell) group by 1""",
        "subset_difference": lagging("select run_id, (b - a)::DOUBLE d_hat from x"),
        "full_transfer_bytes": f"with {base(points)}, {SIZES}, {ledger(FULL)} select * from summary",
        "digest_exchange_bytes": f"with {base(points)}, {SIZES}, {ledger(DIGESTS)} select * from summary",
        "overhead_by_similarity": f"{measured} select *, round(case when minimum_bytes > 0 then total_bytes / minimum_bytes end, 6) overhead_ratio from x",
        "crossover": f"{measured} {crossing('full_transfer', 'syndrome_sketch')} union all {crossing('full_transfer', 'digest_exchange')}",
        "bytes_by_kind": f"with {base(points)}, {SIZES}, k as ({kinds}) select \"method\", phase, kind, sum(bytes) bytes, sum(messages)::BIGINT messages from k group by rollup (\"method\", phase, kind)",
        "key_semijoin": f"""{semijoin_rows()} select 'ship_all' "method", 0::DOUBLE sent_bytes, count(*) rows_shipped, sum(b)::BIGINT row_bytes, sum(b)::DOUBLE total_bytes from w
            union all select 'key_semijoin', (select 8 * count(distinct k) from urgent)::DOUBLE, count(*), sum(b)::BIGINT, (select 8 * count(distinct k) from urgent)::DOUBLE + sum(b) from w where k in (select k from urgent)""",
        "filter_semijoin": filter_semijoin_sql(),
        "sliced_semijoin_trace": sliced_trace_sql(),
        "sliced_semijoin_join": f"{semijoin_rows()} select lines.* from lines join urgent using (k)",
        "lagging_replica_events": lagging("select run_id, a n_a, b n_b, b - a d, round(a / b, 9) jaccard from x"),
        "outage_events": "select -1 side, count(*) n from events where ts >= '2024-01-20' and ts < '2024-01-22' union all select 1, count(*) from events where ts >= '2024-01-05' and ts < '2024-01-08'",
        "worked_ranges": """with k as (select distinct o_orderkey k from orders where o_orderkey is not null), l as (select k from k except (select k from k order by k desc limit 2)),
            r as (select k from k except (select k from k order by k limit 2))
            select 'ranges' run_id, k::BIGINT digest, -1::INT side from (select k from l except select k from r) union all select 'ranges', k::BIGINT, 1::INT from (select k from r except select k from l)""",
        "windowed_cells": "select strftime(date_trunc('day', ts), '%Y-%m-%dT%H:%M') run_id, count(*) filter (where event_id % 50 = 0) missing, count(*) filter (where event_id % 50 = 0) > 0 differs from events group by 1",
        "session_sizes": session,
        "latest_user_events": "select user_id, event_id from events where ts <= '2024-01-15' qualify row_number() over (partition by user_id order by ts desc, event_id desc) = 1",
        "sql_functions": f"with e as (select distinct {h('o_orderkey::varchar')} digest from orders), m as (select ceil(count(*) / {LN2})::BIGINT m from e) select slice, m, count(distinct {pos1}) set_bits from e, m, range(3) t(slice) group by 1, 2",
        "probe_then_sync": result(points),
        "wide_digest_difference": "select count(*) only_right from (select distinct o_orderkey, o_custkey from orders where o_orderkey % 10 = 0)",
    }
