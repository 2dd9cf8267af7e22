"""All queries of the discovery engine with their SQL: one for each method, variant, baseline, measure and workload."""

from __future__ import annotations

from itertools import combinations

from pyspark.sql import functions as F
from pyspark.sql.window import Window

from depmine.functions.bits import names
from depmine.functions.register import register as register_functions
from depmine.operators import cover, distribute, evidence, partition, predicates, refine, relational
from depmine.plans import baselines, cost, lattice, pairs, planner, reason, tree, workloads
from depmine.plans.result import FD
from depmine.sources.io import materialize
from depmine.sources.views import relation, table
from depmine.streaming import monitor

ATTRS = {
    "region": ["r_regionkey", "r_name"],
    "nation": ["n_nationkey", "n_name", "n_regionkey"],
    "supplier": ["s_suppkey", "s_name", "s_nationkey", "s_acctbal"],
    "customer": ["c_custkey", "c_name", "c_nationkey", "c_acctbal", "c_mktsegment"],
    "part": ["p_partkey", "p_name", "p_brand", "p_type", "p_size", "p_retailprice"],
    "orders": ["o_orderkey", "o_custkey", "o_orderstatus", "o_totalprice", "o_orderdate", "o_orderpriority"],
    "lineitem": ["l_orderkey", "l_partkey", "l_suppkey", "l_linenumber", "l_quantity", "l_extendedprice", "l_discount", "l_tax", "l_returnflag", "l_linestatus", "l_shipdate"],
    "events": ["event_id", "ts", "user_id", "event_type", "value", "props"],
    "documents": ["doc_id", "text", "lang", "source", "n_chars"],
    "labels": ["doc_id", "quality", "toxic"],
    "conversations": ["conv_id", "turn", "role", "text"],
    "pages": ["page_id", "url", "html"],
    "benchmark": ["item_id", "text"],
}
QUERIES, SQL = {}, {}


def register(name, run, sql=None):
    QUERIES[name] = run
    if sql:
        SQL[name] = sql


# -- SQL by the definitions ------------------------------------------------


def counts_sql(source: str, attrs: list[str], sizes) -> str:
    """(mask, n, lhs, size): the classes of every attribute set of these sizes; null equals null."""
    rows = []
    for s in sizes:
        for c in combinations(range(len(attrs)), s):
            mask = sum(1 << i for i in c)
            n = f"(select count(*) from (select distinct {', '.join(attrs[i] for i in c)} from src))" if c else "(select least(1, count(*)) from src)"
            rows.append(f"select {mask} as mask, {n} as n, '{names(mask, attrs)}' as lhs, {s} as size")
    return f"with src as ({source}), c as ({' union all '.join(rows)})"


def fd_sql(source: str, attrs: list[str], max_lhs: int | None = None) -> str:
    top = len(attrs) - 1 if max_lhs is None else min(max_lhs, len(attrs) - 1)
    bits = ", ".join(f"({1 << i}, '{a}')" for i, a in enumerate(attrs))
    return f"""{counts_sql(source, attrs, range(top + 2))}, a(bit, name) as (values {bits}),
fd as (select x.mask, x.lhs, x.size, a.bit, a.name from c x, a, c y where x.size <= {top} and (x.mask & a.bit) = 0 and y.mask = (x.mask | a.bit) and y.n = x.n)
select lhs, name as rhs, size as lhs_size from fd f
where not exists (select 1 from fd g where g.bit = f.bit and g.mask <> f.mask and (g.mask & f.mask) = g.mask)"""


def ucc_sql(source: str, attrs: list[str]) -> str:
    return f"""{counts_sql(source, attrs, range(len(attrs) + 1))},
u as (select * from c where n = (select count(*) from src))
select lhs, size as lhs_size from u where not exists (select 1 from u v where v.mask <> u.mask and (v.mask & u.mask) = v.mask)"""


def mask_sql(attrs: list[str], l: str = "l", r: str = "r") -> str:  # noqa: E741
    return " + ".join(f"case when {l}.{a} is not distinct from {r}.{a} then 0 else {1 << i} end" for i, a in enumerate(attrs))


# -- functional dependencies and unique combinations ------------------------------------------------


def fd_query(name, attrs=None, where=None, kind="fd", **options):
    def run(spark, sf_dir):
        df = relation(spark, sf_dir, name).select(*(attrs or ATTRS[name]))
        return planner.whole(df.where(where) if where else df, kind, **options).dependencies

    return run


SMALL = ("region", "nation", "supplier", "customer", "part", "orders", "events", "documents", "labels", "conversations")
for t in SMALL:
    register(f"fd_{t}_lattice_rescan_spill", fd_query(t), fd_sql(f"select * from {t}", ATTRS[t]))
for t in (*SMALL, "pages", "benchmark"):
    register(f"ucc_{t}_lattice", fd_query(t, kind="ucc"), ucc_sql(f"select * from {t}", ATTRS[t]))
for t in ("orders", "part"):
    oracle = fd_sql(f"select * from {t}", ATTRS[t])
    for memory in ("resident", "spill", "chunked"):
        register(f"fd_{t}_lattice_reuse_{memory}", fd_query(t, method="lattice", plan="reuse", memory=memory), oracle)
    register(f"fd_{t}_lattice_rescan_resident", fd_query(t, plan="rescan", memory="resident"), oracle)
    register(f"fd_{t}_lattice_rescan_one_by_one", fd_query(t, strategy="one_by_one"), oracle)
    register(f"fd_{t}_lattice_rescan_fingerprint", fd_query(t, strategy="fingerprint"), oracle)
    for method in ("pair", "hybrid"):
        for plan in ("reuse", "rescan"):
            for memory in ("resident", "spill"):
                register(f"fd_{t}_{method}_{plan}_{memory}", fd_query(t, method=method, plan=plan, memory=memory), oracle)
    register(f"fd_{t}_pair_reuse_resident_deduped", fd_query(t, method="pair", plan="reuse", memory="resident", dedupe=True), oracle)
    register(f"fd_{t}_pair_covers_in_tasks", fd_query(t, method="pair", memory="resident", covers_in="tasks"), oracle)
    register(f"fd_{t}_hybrid_no_sampling", fd_query(t, method="hybrid", data_phase=False), oracle)
    register(f"fd_{t}_hybrid_key_pruning", fd_query(t, method="hybrid", prune_keys=True), oracle)
for plan in ("reuse", "rescan"):
    for memory in ("resident", "spill"):
        register(f"ucc_orders_hybrid_{plan}_{memory}", fd_query("orders", kind="ucc", method="hybrid", plan=plan, memory=memory), SQL["ucc_orders_lattice"])
        register(f"ucc_part_pair_{plan}_{memory}", fd_query("part", kind="ucc", method="pair", plan=plan, memory=memory), SQL["ucc_part_lattice"])
LINE = fd_sql("select * from lineitem", ATTRS["lineitem"])
register("fd_lineitem_lhs3_lattice_rescan_spill", fd_query("lineitem", max_lhs=3), fd_sql("select * from lineitem", ATTRS["lineitem"], 3))
register("fd_lineitem_lattice_rescan_resident", fd_query("lineitem", memory="resident"), LINE)
register("fd_lineitem_hybrid_rescan_resident", fd_query("lineitem", method="hybrid", memory="resident"), LINE)
register("fd_lineitem_lhs3_hybrid_rescan_spill", fd_query("lineitem", method="hybrid", max_lhs=3), fd_sql("select * from lineitem", ATTRS["lineitem"], 3))
register("fd_lineitem_lhs3_hybrid_reuse_resident", fd_query("lineitem", method="hybrid", plan="reuse", memory="resident", max_lhs=3), fd_sql("select * from lineitem", ATTRS["lineitem"], 3))
register("ucc_lineitem_lattice", fd_query("lineitem", kind="ucc", memory="resident"), ucc_sql("select * from lineitem", ATTRS["lineitem"]))
STAR = ["o_orderkey", "o_custkey", "o_orderstatus", "o_orderpriority", "c_custkey", "c_name", "c_nationkey", "c_mktsegment", "n_nationkey", "n_name", "n_regionkey"]
STAR_SQL = "select * from orders join customer on o_custkey = c_custkey join nation on c_nationkey = n_nationkey"
STAR_ALL = [*ATTRS["orders"], *ATTRS["customer"], *ATTRS["nation"]]
register("fd_star14_lattice_rescan_resident", fd_query("star14", attrs=STAR_ALL, memory="resident"))
register("fd_star14_lattice_reuse_resident", fd_query("star14", attrs=STAR_ALL, plan="reuse", memory="resident"))
register("fd_star14_hybrid_rescan_resident", fd_query("star14", attrs=STAR_ALL, method="hybrid", memory="resident"))
register("fd_star14_lhs2_lattice_rescan_spill", fd_query("star14", attrs=STAR_ALL, max_lhs=2), fd_sql(STAR_SQL, STAR_ALL, 2))
register("fd_star14_lhs2_hybrid_rescan_resident", fd_query("star14", attrs=STAR_ALL, method="hybrid", memory="resident", max_lhs=2), fd_sql(STAR_SQL, STAR_ALL, 2))
WIDE_SQL = "select l.*, o.* exclude (o_orderkey), c.* exclude (c_custkey), s.* exclude (s_suppkey), n_name as s_nation from lineitem l join orders o on l_orderkey = o_orderkey join customer c on o_custkey = c_custkey join supplier s on l_suppkey = s_suppkey join nation on s_nationkey = n_nationkey"
WIDE_ALL = [*ATTRS["lineitem"], *ATTRS["orders"][1:], *ATTRS["customer"][1:], *ATTRS["supplier"][1:], "s_nation"]
register("fd_wide24_lattice_rescan_resident", fd_query("wide24", attrs=WIDE_ALL, memory="resident"))
register("fd_wide24_lhs1_lattice_rescan_spill", fd_query("wide24", attrs=WIDE_ALL, max_lhs=1), fd_sql(WIDE_SQL, WIDE_ALL, 1))

# values whose text and whose equality differ: instants below a millisecond, NaN, -0.0, null

ODD_SQL = """select timestamp '2024-01-01 00:00:00' + to_microseconds(event_id // 3) as t, case when event_id % 5 = 0 then null when event_id % 5 = 1 then 'nan'::double else (event_id % 7)::double * (event_id % 3 - 1)::double end as z,
event_id // 3 % 50 as a, user_id % 4 as b, event_type from events"""
ODD = ["t", "z", "a", "b", "event_type"]


def odd_values(spark, sf_dir):
    """Events with instants one microsecond apart, with 0.0 and -0.0, NaN and null among the numbers."""
    e = table(spark, sf_dir, "events")
    third = F.floor(F.col("event_id") / 3)
    z = F.when(F.col("event_id") % 5 == 0, F.lit(None).cast("double")).when(F.col("event_id") % 5 == 1, F.lit(float("nan"))).otherwise((F.col("event_id") % 7).cast("double") * (F.col("event_id") % 3 - 1).cast("double"))
    return e.select(F.timestamp_micros(F.lit(1_704_067_200_000_000) + third).alias("t"), z.alias("z"), (third % 50).alias("a"), (F.col("user_id") % 4).alias("b"), "event_type")


def odd_query(kind="fd", **options):
    return lambda spark, sf_dir: planner.whole(odd_values(spark, sf_dir), kind, **options).dependencies


for memory in ("resident", "spill", "chunked"):
    register(f"fd_events_lattice_reuse_{memory}", fd_query("events", plan="reuse", memory=memory), SQL["fd_events_lattice_rescan_spill"])
    register(f"ucc_events_lattice_reuse_{memory}", fd_query("events", kind="ucc", plan="reuse", memory=memory), SQL["ucc_events_lattice"])
    register(f"fd_odd_values_lattice_reuse_{memory}", odd_query(plan="reuse", memory=memory), fd_sql(ODD_SQL, ODD))
for memory in ("resident", "spill"):
    register(f"fd_odd_values_lattice_rescan_{memory}", odd_query(memory=memory), fd_sql(ODD_SQL, ODD))
    register(f"fd_odd_values_hybrid_rescan_{memory}", odd_query(method="hybrid", memory=memory), fd_sql(ODD_SQL, ODD))

# -- order dependencies ------------------------------------------------


def od_sql(t: str, attrs: list[str], desc: bool) -> str:
    far, near, op = ("min(lo)", "hi", "<") if desc else ("max(hi)", "lo", ">")
    parts = []
    for a in attrs:
        for b in attrs:
            if a != b:
                parts.append(f"""select '{a}' as lhs, '{b}' as rhs, '{"desc" if desc else "asc"}' as direction, 'list' as kind
where not exists (select 1 from (select lo, hi, {far} over (order by {a} rows between unbounded preceding and 1 preceding) as reach from (select {a}, min({b}) as lo, max({b}) as hi from {t} group by {a})) where lo <> hi or reach {op} {near})""")
    return " union all ".join(parts)


def od_query(t, directions, **options):
    return lambda spark, sf_dir: planner.order_dependencies(table(spark, sf_dir, t).select(*ATTRS[t]), ATTRS[t], directions=directions, **options)


for t in ("events", "customer", "supplier", "region"):
    for d in ("asc", "desc"):
        register(f"od_{t}_unary_{d}", od_query(t, (d,)), od_sql(t, ATTRS[t], d == "desc"))
register("od_supplier_unary_reuse_resident", od_query("supplier", ("asc",), plan="reuse", memory="resident"), SQL["od_supplier_unary_asc"])
register("od_supplier_unary_rescan_resident", od_query("supplier", ("asc",), memory="resident"), SQL["od_supplier_unary_asc"])


def lattice_od_sql(t: str, attrs: list[str], directions=("asc", "desc")) -> str:
    """Minimal set-based dependencies over all contexts, by their definitions."""
    m, cons, comps = len(attrs), [], []
    for size in range(m):
        for c in combinations(range(m), size):
            mask, columns = sum(1 << i for i in c), [attrs[i] for i in c]
            group = f" group by {', '.join(columns)}" if c else ""
            for a in (i for i in range(m) if i not in c):
                cons.append(f"select {mask} as ctx, {a} as a where not exists (select 1 from {t}{group} having count(distinct {attrs[a]}) > 1)")
            for a, b in combinations([i for i in range(m) if i not in c], 2):
                part = f"partition by {', '.join(columns)} " if c else ""
                for d in directions:
                    far, near, op = ("min(lo)", "hi", "<") if d == "desc" else ("max(hi)", "lo", ">")
                    comps.append(f"""select {mask} as ctx, {a} as a, {b} as b, '{d}' as direction where not exists (select 1 from (select lo, hi, {far} over ({part}order by {attrs[a]} rows between unbounded preceding and 1 preceding) as reach
from (select {', '.join([*columns, attrs[a]])}, min({attrs[b]}) as lo, max({attrs[b]}) as hi from {t} group by {', '.join([*columns, attrs[a]])})) where reach {op} {near})""")
    named = ", ".join(f"({sum(1 << i for i in c)}, '{names(sum(1 << i for i in c), attrs)}')" for size in range(m) for c in combinations(range(m), size))
    one = ", ".join(f"({i}, '{a}')" for i, a in enumerate(attrs))
    return f"""with con as ({' union all '.join(cons)}), comp as ({' union all '.join(comps)}), s(mask, lhs) as (values {named}), n(i, name) as (values {one})
select lhs, name as rhs, 'asc' as direction, 'constant' as kind from con k join s on mask = ctx join n on i = a where not exists (select 1 from con o where o.a = k.a and o.ctx <> k.ctx and (o.ctx & k.ctx) = o.ctx)
union all select lhs, x.name || '~' || y.name, direction, 'compatible' from comp k join s on mask = ctx join n x on x.i = a join n y on y.i = b
where not exists (select 1 from con o where o.a in (k.a, k.b) and (o.ctx & k.ctx) = o.ctx) and not exists (select 1 from comp o where o.a = k.a and o.b = k.b and o.direction = k.direction and o.ctx <> k.ctx and (o.ctx & k.ctx) = o.ctx)"""


for t in ("nation", "supplier", "customer", "part", "orders"):
    sql = lattice_od_sql(t, ATTRS[t])
    register(f"od_{t}_lattice_rescan_resident", od_query(t, ("asc", "desc"), lists=False, memory="resident"), sql)
    if t in ("nation", "supplier", "customer"):
        register(f"od_{t}_lattice_rescan_spill", od_query(t, ("asc", "desc"), lists=False), sql)
for memory in ("resident", "spill"):
    register(f"od_supplier_lattice_reuse_{memory}", od_query("supplier", ("asc", "desc"), lists=False, plan="reuse", memory=memory), SQL["od_supplier_lattice_rescan_spill"])
register("od_nation_context1", od_query("nation", ("asc", "desc"), lists=False, max_context=1), SQL["od_nation_lattice_rescan_spill"])


def od_swaps(spark, sf_dir):
    return refine.swaps(table(spark, sf_dir, "lineitem"), ["l_returnflag"], "l_quantity", "l_discount").groupBy("l_returnflag").agg(F.count("*").alias("n_swaps"))


register("od_lineitem_compat_slice", od_swaps, """select l_returnflag, count(*) as n_swaps from (select l_returnflag, lo, max(hi) over (partition by l_returnflag order by l_quantity rows between unbounded preceding and 1 preceding) as reach
from (select l_returnflag, l_quantity, min(l_discount) as lo, max(l_discount) as hi from lineitem group by 1, 2)) where reach > lo group by 1""")

# -- denial constraints ------------------------------------------------

DC_OPS = {"": (15, ()), "=": (2, ("<=", ">=", "")), "!=": (13, ("",)), "<": (1, ("<=", "!=")), "<=": (3, ("",)), ">": (4, (">=", "!=")), ">=": (6, ("",))}
DC_TEXTS = {"part": ("p_name", "p_brand", "p_type"), "orders": ("o_orderstatus", "o_orderpriority"), "customer": ("c_name", "c_mktsegment"), "supplier": ("s_name",)}


def dc_sql(t: str, attrs: list[str], most: int = 5) -> str:
    """Minimal constraints over same-attribute predicates: every choice of at most one comparison an attribute, tested on the distinct comparison results of all pairs.

    An outcome is 0 less, 1 equal, 2 greater, 3 neither; an operator is the set of outcomes that satisfy it. A valid choice is minimal if no choice with one comparison weakened or dropped is valid."""
    ops = list(DC_OPS)
    code = " + ".join(f"(case when l.{a} = r.{a} then 1 " + ("else 3" if a in DC_TEXTS[t] else f"when l.{a} < r.{a} then 0 else 2") + f" end) * {4**i}" for i, a in enumerate(attrs))
    flip = {"<": ">", ">": "<", "<=": ">=", ">=": "<="}
    values = ", ".join(f"({n}, '{o}', '{flip.get(o, o)}', {DC_OPS[o][0]})" for n, o in enumerate(ops))
    steps = ", ".join(f"({ops.index(o)}, {ops.index(w)})" for o in ops for w in DC_OPS[o][1])
    few = ", ".join(f"(select * from o where op not in ('<', '<=', '>', '>=')) o{i}" if a in DC_TEXTS[t] else f"o o{i}" for i, a in enumerate(attrs))
    order = sorted(range(len(attrs)), key=lambda i: attrs[i])
    said = lambda op: "concat_ws(' and ', " + ", ".join(f"case when o{i}.n > 0 then 't1.{attrs[i]} ' || o{i}.{op} || ' t2.{attrs[i]}' end" for i in order) + ")"
    size = " + ".join(f"(o{i}.n > 0)::int" for i in range(len(attrs)))
    number = " + ".join(f"o{i}.n * {7**i}" for i in range(len(attrs)))
    held = " and ".join(f"(m{i} >> ((p.code >> {2 * i}) & 3)) & 1 = 1" for i in range(len(attrs)))
    weaker = " union all ".join(f"select v.number, v.number + (w.d - v.n{i}) * {7**i} as down from v join w on w.u = v.n{i}" for i in range(len(attrs)))
    return f"""with src as (select row_number() over () as rid, * from {t}), p as (select distinct {code} as code from src l, src r where l.rid <> r.rid),
o(n, op, flip, mask) as (values {values}), w(u, d) as (values {steps}),
c as (select {number} as number, {size} as size, {said('op')} as dc, {said('flip')} as mirror, {', '.join(f'o{i}.n as n{i}, o{i}.mask as m{i}' for i in range(len(attrs)))} from {few}),
v as (select * from c where size between 1 and {most} and not exists (select 1 from p where {held})), down as ({weaker})
select distinct least(dc, mirror) as dc, size::int as n_predicates from v where not exists (select 1 from down d join v u on u.number = d.down where d.number = v.number)"""


def dc_query(t, **options):
    return lambda spark, sf_dir: planner.denial_constraints(table(spark, sf_dir, t).select(*ATTRS[t]), ATTRS[t], **options)


DC = {t: dc_sql(t, ATTRS[t]) for t in DC_TEXTS}
for method in ("pair", "hybrid"):
    for plan in ("reuse", "rescan"):
        for memory in ("resident", "spill"):
            register(f"dc_part_{method}_{plan}_{memory}", dc_query("part", method=method, plan=plan, memory=memory), DC["part"])
            register(f"dc_customer_{method}_{plan}_{memory}", dc_query("customer", method=method, plan=plan, memory=memory), DC["customer"])
register("dc_part_covers_in_tasks", dc_query("part", covers_in="tasks"), DC["part"])
register("dc_orders_hybrid_rescan_resident", dc_query("orders", method="hybrid"), DC["orders"])
register("dc_orders_pair_rescan_resident", dc_query("orders"), DC["orders"])
register("dc_supplier_wide_space", dc_query("supplier", cross=True, single=True, overlap=0.0, max_predicates=3))
register("dc_supplier_wide_space_hybrid", dc_query("supplier", method="hybrid", cross=True, single=True, overlap=0.0, max_predicates=3))


def q_predicates(spark, sf_dir):
    """The predicate space of lineitem: comparisons of one attribute, of two attributes across rows and within one row."""
    space = predicates.space_of(table(spark, sf_dir, "lineitem"), ATTRS["lineitem"], cross=True, single=True)
    kinds = [("same" if s.left[1] == s.right[1] else "single" if s.single else "cross", s.left[1], s.right[1], op) for s in space.slots for op in s.ops]
    return spark.createDataFrame(kinds, "kind string, left_attr string, right_attr string, op string").groupBy("kind").agg(F.count("*").alias("n_predicates"))


NUMBERS = ["l_orderkey", "l_partkey", "l_suppkey", "l_linenumber", "l_quantity", "l_extendedprice", "l_discount", "l_tax"]
_PAIRS = list(combinations(NUMBERS, 2))
register("predicate_space_lineitem", q_predicates, "with s as (" + " union all ".join(f"select (select count(distinct {a}) from lineitem where {a}::double in (select {b}::double from lineitem)) >= 0.3 * least((select count(distinct {a}) from lineitem), (select count(distinct {b}) from lineitem)) as shared" for a, b in _PAIRS) + ") select 'same' as kind, 58::bigint as n_predicates union all select kind, count(*) * 12 from s, (values ('cross'), ('single')) t(kind) where shared group by 1")
CHECK = [("o_custkey", "="), ("o_totalprice", "<"), ("o_orderdate", ">")]
register(
    "dc_violations_orders",
    lambda spark, sf_dir: reason.dc_violations(table(spark, sf_dir, "orders"), CHECK, "o_orderkey"),
    "select a.o_orderkey as t1, b.o_orderkey as t2 from orders a join orders b on a.o_custkey = b.o_custkey and a.o_totalprice < b.o_totalprice and a.o_orderdate > b.o_orderdate",
)

# -- primitives ------------------------------------------------


def q_classes(spark, sf_dir):
    return partition.classes_from_rows(table(spark, sf_dir, "orders"), ["o_orderstatus", "o_orderpriority"], "o_orderkey")


register("classes_orders", q_classes, "select min(o_orderkey) over (partition by o_orderstatus, o_orderpriority) as class_id, o_orderkey as row_id from orders")


def level_counts(strategy):
    def run(spark, sf_dir):
        attrs = ATTRS["lineitem"]
        masks = [1 << i | 1 << j for i, j in combinations(range(len(attrs)), 2)]
        df = table(spark, sf_dir, "lineitem")
        counts = partition.counts_broadcast(df, attrs, masks, 8) if strategy == "broadcast" else getattr(partition, f"counts_{strategy}")(df, attrs, masks)
        return spark.createDataFrame([(names(x, attrs), n) for x, n in counts.items()], "lhs string, n_classes long")

    return run


LEVEL2 = counts_sql("select * from lineitem", ATTRS["lineitem"], [2]) + " select lhs, n as n_classes from c"
for strategy in ("by_grouping_sets", "by_fingerprint", "one_by_one", "broadcast"):
    register(f"class_counts_lineitem_level2_{strategy}", level_counts(strategy), LEVEL2)


def q_intersect(spark, sf_dir):
    attrs = ATTRS["orders"]
    store = materialize(partition.column_classes(table(spark, sf_dir, "orders"), attrs, "o_orderkey"), "classes")
    made = partition.intersect(store, spark.createDataFrame([(0, 2, 5)], "node int, left int, right int"))
    return made.select("class_id", "row_id")


register("intersect_orders", q_intersect, SQL["classes_orders"])


def q_evidence(t, plan="rescan", memory="resident"):
    def run(spark, sf_dir):
        attrs = ATTRS[t]
        rows, _, n = pairs.compacted(table(spark, sf_dir, t).select(*attrs), attrs)
        return pairs.evidence_of(rows, n, attrs, plan, memory, 8)

    key = ATTRS[t][0]
    return run, f"select {mask_sql(ATTRS[t])} as ev0, count(*) as n_pairs from {t} l join {t} r on l.{key} < r.{key} group by 1"


for t in ("orders", "customer", "part"):
    register(f"evidence_hist_{t}", *q_evidence(t))
register("evidence_hist_part_cartesian", q_evidence("part", memory="spill")[0], q_evidence("part")[1])
SHARE = " or ".join(f"l.{a} is not distinct from r.{a}" for a in ATTRS["part"])


def q_shared(dedupe):
    def run(spark, sf_dir):
        rows, _, _ = pairs.compacted(table(spark, sf_dir, "part"), ATTRS["part"])
        return evidence.histogram(pairs.pairs_of(rows, ATTRS["part"], "reuse", "resident", 8, dedupe), evidence.differs(ATTRS["part"]))

    return run


register("evidence_hist_part_blocks_deduped", q_shared(True), f"select {mask_sql(ATTRS['part'])} as ev0, count(*) as n_pairs from part l join part r on l.p_partkey < r.p_partkey where {SHARE} group by 1")
register("evidence_hist_part_blocks", q_shared(False), f"select {mask_sql(ATTRS['part'])} as ev0, sum({' + '.join(f'(l.{a} is not distinct from r.{a})::int' for a in ATTRS['part'])})::bigint as n_pairs from part l join part r on l.p_partkey < r.p_partkey where {SHARE} group by 1")


def q_sorted(spark, sf_dir):
    return cover.sorted_evidence(q_evidence("part")[0](spark, sf_dir)).select("ev0", "n_attrs")


register("sorted_evidence_part", q_sorted, f"select distinct {mask_sql(ATTRS['part'])} as ev0, bit_count({mask_sql(ATTRS['part'])})::int as n_attrs from part l join part r on l.p_partkey < r.p_partkey")
register("refine_orders", lambda spark, sf_dir: refine.by_minmax(table(spark, sf_dir, "orders"), ["o_totalprice"], ["o_orderstatus", "o_orderpriority", "o_custkey", "o_orderdate"]), " union all ".join(f"select '{a}' as rhs, not exists (select 1 from orders group by o_totalprice having count(distinct {a}) > 1) as holds" for a in ("o_orderstatus", "o_orderpriority", "o_custkey", "o_orderdate")))
register("witness_customer", lambda spark, sf_dir: refine.witness(table(spark, sf_dir, "customer"), ["c_mktsegment"], "c_nationkey"), "select c_mktsegment, min(c_nationkey) as value_1, max(c_nationkey) as value_2 from customer group by 1 having min(c_nationkey) <> max(c_nationkey)")


def q_covers(spark, sf_dir):
    seen = evidence.masks(q_evidence("part")[0](spark, sf_dir))
    found = cover.per_rhs(spark, seen, 6, where="tasks")
    return spark.createDataFrame([(names(x, ATTRS["part"]), names(a, ATTRS["part"]), x.bit_count()) for x, a in found], FD)


register("covers_part", q_covers, SQL["fd_part_lattice_rescan_spill"])
register("next_level_orders", lambda spark, sf_dir: lattice.next_level_df(spark.createDataFrame([(x,) for x in (3, 5, 9, 6, 10, 33)], "mask long")), "select * from (values (7::bigint), (11::bigint)) t(mask)")
USAGE = {"lattice_fd": "P1,P3,P4", "lattice_ucc": "P1,P3,P4", "lattice_od": "P1,P3,P4,P6", "pair_fd": "P1,P2,P4,P5,P6", "pair_dc": "P2,P4,P5,P6", "hybrid_fd": "P1,P2,P3,P4,P5,P6", "hybrid_ucc": "P1,P2,P3,P4,P5,P6", "hybrid_dc": "P1,P2,P4,P5,P6"}
register("usage_matrix", lambda spark, sf_dir: spark.createDataFrame(list(USAGE.items()), "method string, primitives string"), "select * from (values " + ", ".join(f"('{k}', '{v}')" for k, v in USAGE.items()) + ") t(method, primitives)")

# -- distribution and cost ------------------------------------------------


def anchored(spark, sf_dir):
    return table(spark, sf_dir, "orders").select("o_orderkey", "o_orderstatus")


def anchor():
    return F.pmod(F.col("o_orderkey"), F.lit(4))


RIDE = "with o as (select o_orderkey, o_orderkey % 4 as a from orders)"
register("triangle_pairs_orders", lambda spark, sf_dir: distribute.triangle(anchored(spark, sf_dir), 10, ["o_orderkey"], anchor()).agg(F.count("*").alias("n_pairs"), F.sum(F.least("l_o_orderkey", "r_o_orderkey") * F.greatest("l_o_orderkey", "r_o_orderkey")).alias("check_sum")), "select count(*) as n_pairs, sum(l.o_orderkey * r.o_orderkey)::bigint as check_sum from orders l join orders r on l.o_orderkey < r.o_orderkey")


def q_triangle_load(spark, sf_dir):
    df = anchored(spark, sf_dir)
    routed = distribute.route(df, 4, anchor())
    return distribute.load_of(distribute.triangle(df, 10, ["o_orderkey"], anchor()), routed, "cell", 2).select(F.col("worker").cast("long").alias("worker"), "x", "y")


register("xy_triangle_orders", q_triangle_load, RIDE + """, cells as (select least(a, b) * 4 + greatest(a, b) as worker, o_orderkey from o, range(4) t(b)),
x as (select worker, count(*) * 2 as x from cells group by 1),
y as (select least(l.a, r.a) * 4 + greatest(l.a, r.a) as worker, count(*) * 2 as y from o l join o r on l.o_orderkey < r.o_orderkey group by 1)
select worker::bigint as worker, x, coalesce(y, 0) as y from x left join y using (worker)""")
register("triangle_meters_orders", lambda spark, sf_dir: cost.maxima(q_triangle_load(spark, sf_dir)), SQL["xy_triangle_orders"].replace("select worker::bigint as worker, x, coalesce(y, 0) as y from x", "select max(x)::bigint as meter_x, max(coalesce(y, 0))::bigint as meter_y, sum(x)::bigint as total_x, sum(coalesce(y, 0))::bigint as total_y from x"))
register("block_stats_lineitem", lambda spark, sf_dir: distribute.block_stats(table(spark, sf_dir, "lineitem").select("l_returnflag", "l_linenumber", "l_tax"), ["l_returnflag", "l_linenumber", "l_tax"]).select("attr", "size", "work"), " union all ".join(f"select {i}::int as attr, count(*) as size, (count(*) * (count(*) - 1) // 2)::bigint as work from lineitem group by {a} having count(*) > 1" for i, a in enumerate(("l_returnflag", "l_linenumber", "l_tax"))))
register("band_deal_orders", lambda spark, sf_dir: distribute.band_deal(table(spark, sf_dir, "orders").groupBy("o_custkey").agg(F.count("*").alias("size")), 8, tie=["o_custkey"]).select("o_custkey", "size", "worker"), "select o_custkey, size, ((row_number() over (order by size, o_custkey) - 1) % 8)::int as worker from (select o_custkey, count(*) as size from orders group by 1)")
register("columns_deal_lineitem", lambda spark, sf_dir: distribute.dealt_columns(table(spark, sf_dir, "lineitem"), ATTRS["lineitem"], 4), " union all ".join(f"select '{a}' as attr, {i % 4} as worker, count({a}) as n_values from lineitem" for i, a in enumerate(ATTRS["lineitem"])))
register("group_schedule_k10", lambda spark, sf_dir: spark.createDataFrame(distribute.group_schedule(10, 10), "g1 int, g2 int, round int").groupBy("round").agg(F.count("*").alias("n_pairs"), F.count_distinct("g1", "g2").alias("n_distinct")), "select r::int as round, least(10, 55 - r * 10) as n_pairs, least(10, 55 - r * 10) as n_distinct from range(6) t(r)")


def q_groups(spark, sf_dir):
    rows = distribute.with_groups(anchored(spark, sf_dir), 6, ["o_orderkey"])
    done = distribute.group_pairs(rows, [(a, b) for a, b, _ in distribute.group_schedule(6, 6)], ["o_orderkey"])
    return done.agg(F.count("*").alias("n_pairs"), F.sum(F.col("l_o_orderkey") * F.col("r_o_orderkey")).alias("check_sum"))


register("pair_schedule_4096", lambda spark, sf_dir: schedule_ends(spark), "select 4096 as n_groups, 8390656::bigint as n_pairs, 1048832::bigint as n_rounds, 8 as first_round, 8 as last_round, 16 as n_distinct")


def schedule_ends(spark):
    """A schedule of millions of pairs, of which only two rounds are made."""
    schedule = distribute.PairSchedule(4096, 8)
    first, last = schedule.round(0), schedule.round(schedule.rounds - 1)
    return spark.createDataFrame([(4096, schedule.total, schedule.rounds, len(first), len(last), len({*first, *last}))], "n_groups int, n_pairs long, n_rounds long, first_round int, last_round int, n_distinct int")


register("group_pairs_orders", q_groups, SQL["triangle_pairs_orders"])


def q_window(mode):
    return lambda spark, sf_dir: distribute.window_pairs(table(spark, sf_dir, "orders").select("o_orderkey", "o_custkey"), "o_custkey", 2, ["o_orderkey"], mode).select("l_o_orderkey", "r_o_orderkey")


WINDOWED = "select * from (select o_orderkey as l_o_orderkey, lead(o_orderkey, 2) over (partition by o_custkey order by o_orderkey) as r_o_orderkey from orders) where r_o_orderkey is not null"
register("window_pairs_orders_lead", q_window("lead"), WINDOWED)
register("window_pairs_orders_join", q_window("join"), WINDOWED)
for t in ("lineitem", "orders", "part", "customer"):
    register(f"w_comparisons_{t}", lambda spark, sf_dir, t=t: cost.work_in_classes(table(spark, sf_dir, t), ATTRS[t]), " union all ".join(f"select '{a}' as attr, coalesce(sum(b * (b - 1) // 2), 0)::bigint as w from (select count(*) as b from {t} group by {a})" for a in ATTRS[t]))


def q_xy_blocks(spark, sf_dir):
    """What the eight workers of the reuse plan receive and compare in all, on part: by the sizes of classes, whatever worker a class goes to."""
    attrs = ATTRS["part"]
    rows, _, _ = pairs.compacted(table(spark, sf_dir, "part"), attrs)
    stats = distribute.block_stats(rows, attrs)
    made = distribute.blocks(rows, attrs, 8, pairs.ORDER).count()
    return stats.agg(F.count("*").alias("n_blocks"), F.sum("size").cast("long").alias("n_members"), F.sum("work").cast("long").alias("w")).withColumn("n_compared", F.lit(made).cast("long"))


register("xy_blocks_part", q_xy_blocks, "with b as (" + " union all ".join(f"select count(*) as size from part group by {a} having count(*) > 1" for a in ATTRS["part"]) + ") select count(*) as n_blocks, sum(size)::bigint as n_members, sum(size * (size - 1) // 2)::bigint as w, sum(size * (size - 1) // 2)::bigint as n_compared from b")


def q_bounds(spark, sf_dir):
    """Counted loads of the busiest of k workers against the bounds, for all four ways to deal pairs, on part.

    The triangle's bound supposes k cells of a grid of side sqrt(2k); a grid of l(l+1)/2 cells exceeds it by sqrt((l+1)/l). Random deals get a tenth on top."""
    attrs, k = ATTRS["part"], 10
    rows, _, n = pairs.compacted(table(spark, sf_dir, "part"), attrs)
    m, w = len(attrs), pairs.within_classes(rows, attrs)
    order, side = pairs.ORDER, distribute.triangle_side(k)
    least = distribute.class_routes(rows, "p_brand", k)
    most = rows.groupBy("p_brand").count().agg(F.max("count")).first()[0]
    classes = rows.groupBy("p_brand").count().where("count > 1").count()
    grouped, own = distribute.with_groups(rows, k, order), distribute.PairSchedule(k, k).round(0)
    left, right = distribute.group_routes(grouped, own)
    found = {
        "triangle": (distribute.load_of(distribute.triangle(rows, k, order), distribute.triangle_routes(rows, k, order), "cell", m), cost.bound("pair", "rescan", "resident", n, m, k), ((side + 1) / side) ** 0.5),
        "blocks": (distribute.load_of(distribute.blocks(rows, attrs, k, order), distribute.block_routes(rows, attrs, k, order), "worker", m), cost.bound("pair", "reuse", "resident", n, m, k, w), 1.0),
        "groups": (distribute.load_of(distribute.group_pairs(grouped, own, order), left.unionByName(right), "cell", m), cost.bound("hybrid", "rescan", "resident", n, m, k), 1.1),
        "bands": (distribute.load_of(distribute.led(least, "p_brand", 1, ["p_partkey"]), least, "worker", m), (-(-classes // k) * m * most,) * 2, 1.0),
    }
    out = []
    for name, (load, (x, y), slack) in found.items():
        top = cost.maxima(load).first()
        out.append((name, top["meter_x"] <= 1.1 * slack * x, top["meter_y"] <= 1.1 * slack**2 * y))
    return spark.createDataFrame(out, "strategy string, x_within boolean, y_within boolean")


register("bounds_vs_counted", q_bounds, "select * from (values ('triangle', true, true), ('blocks', true, true), ('groups', true, true), ('bands', true, true)) t(strategy, x_within, y_within)")


def q_model(spark, sf_dir):
    """The bounds of all plans for lineitem on 55 workers, from its rows, its comparisons within classes and its largest class, rounded."""
    df, m = table(spark, sf_dir, "lineitem"), len(ATTRS["lineitem"])
    held = distribute.block_stats(df, ATTRS["lineitem"]).agg(F.sum("work").alias("w"), F.max("size").alias("b")).first()
    n, w, b = float(df.count()), float(held["w"] or 0), float(held["b"] or 1)
    rows = [(method, plan, memory, *(int(v + 0.5) for v in cost.bound(method, plan, memory, n, float(m), 55.0, w, b))) for method in ("lattice", "pair", "hybrid") for plan in ("reuse", "rescan") for memory in ("resident", "spill")]
    return spark.createDataFrame(rows, "method string, plan string, memory string, x long, y long")


register("cost_bounds_model", q_model, "with held as (" + " union all ".join(f"select sum(n * (n - 1) // 2) as w, max(n) as b from (select count(*) as n from lineitem group by {a})" for a in ATTRS["lineitem"]) + """),
c as (select (select count(*) from lineitem)::double as n, 11.0::double as m, 55.0::double as k, sum(w)::double as w, max(b)::double as b, 2048.0::double as s from held)
select method, plan, memory, round(x)::bigint as x, round(y)::bigint as y from c, lateral (values
('lattice', 'reuse', 'resident', s * n * sqrt(2 / k), s * 2 * n / k), ('lattice', 'reuse', 'spill', s * n, s * 2 * n), ('lattice', 'rescan', 'resident', n * m, n * m * s / k), ('lattice', 'rescan', 'spill', s * n * m / k, n * m * s / k),
('pair', 'reuse', 'resident', 5 * m * m * greatest(n / k, sqrt(2 * w / k)), 5 * m * w / k), ('pair', 'reuse', 'spill', n * m * m, 5 * m * w / k), ('pair', 'rescan', 'resident', n * m * sqrt(2 / k), m * n * n / (2 * k)), ('pair', 'rescan', 'spill', n * m * 2 / sqrt(k), m * n * n / (2 * k)),
('hybrid', 'reuse', 'resident', n * m * b / k, n * m * b / k), ('hybrid', 'reuse', 'spill', n * m * b, n * m * b / k), ('hybrid', 'rescan', 'resident', 2 * n * m / k, m * (n / k) * (n / k)), ('hybrid', 'rescan', 'spill', 2 * n * m / (2 * k), m * (n / (2 * k)) * (n / (2 * k)))) t(method, plan, memory, x, y)""")


def trace_sql(t: str, attrs: list[str]) -> str:
    """Sets of each level and dependencies found so far. The open right sides of X are the A for which no B in X has X\\{A,B} -> B; a set goes on if it has one and is no key, and is made if all its subsets one smaller went on."""
    m = len(attrs)
    return f"""{counts_sql(f'select * from {t}', attrs, range(m + 1))}, b(bit) as (values {', '.join(f'({1 << i})' for i in range(m))}),
r as (select count(*) as n from src), open as (select x.mask, a.bit from c x, b a where x.size > 0 and not exists (select 1 from b, c p, c q where (x.mask & b.bit) > 0 and p.mask = (x.mask & ~a.bit & ~b.bit) and q.mask = (p.mask | b.bit) and p.n = q.n)),
alive as (select mask from c where mask = 0 or (n <> (select n from r) and mask in (select mask from open))),
made as (select x.mask, x.size from c x where x.size > 0 and not exists (select 1 from b where (x.mask & b.bit) > 0 and (x.mask & ~b.bit) not in (select mask from alive))),
fd as ({fd_sql(f'select * from {t}', attrs)}), placed as (select c.size + (c.n <> (select n from r))::int as level, count(*) as n from fd join c on c.lhs = fd.lhs group by 1)
select size as level, count(*) as size, coalesce((select sum(n) from placed where placed.level <= made.size), 0)::bigint as found from made group by made.size"""


def q_trace(t):
    return lambda spark, sf_dir: planner.whole(table(spark, sf_dir, t), memory="resident").trace.select("level", "size", "found")


for t in ("orders", "part", "customer"):
    register(f"lattice_trace_{t}", q_trace(t), trace_sql(t, ATTRS[t]))
register("hybrid_trace_orders", lambda spark, sf_dir: planner.whole(table(spark, sf_dir, "orders"), method="hybrid", memory="resident").trace)
register("phase_seconds_orders", lambda spark, sf_dir: planner.whole(table(spark, sf_dir, "orders"), method="hybrid", plan="reuse", memory="resident").cost)
register("candidate_tree_part", lambda spark, sf_dir: tree_of(spark, sf_dir), SQL["fd_part_lattice_rescan_spill"])


def tree_of(spark, sf_dir):
    t = tree.CandidateTree(6)
    for e in sorted(evidence.masks(q_evidence("part")[0](spark, sf_dir))):
        t.refute(e)
    return spark.createDataFrame([(names(x, ATTRS["part"]), names(a, ATTRS["part"]), x.bit_count()) for x, a in t.items()], FD)


register("limit_status_lineitem", lambda spark, sf_dir: spark.createDataFrame([(m, planner.discover(table(spark, sf_dir, "lineitem"), method=m, memory="resident", **o).status) for m, o in (("lattice", {"limit_s": 0.0}), ("pair", {"max_pairs": 1000}))], "method string, status string"), "select * from (values ('lattice', 'time limit'), ('pair', 'memory limit')) t(method, status)")

# -- baselines and accuracy ------------------------------------------------

NODE = "(l_orderkey * 31 + l_partkey * 17 + l_linenumber * 7) % {k}"


def local_sql(k: int, most: int | None) -> str:
    """The closures of the nodes' dependencies intersected, then minimal ones."""
    attrs = ATTRS["lineitem"]
    top = len(attrs) - 1 if most is None else most
    bits = ", ".join(f"({1 << i}, '{a}')" for i, a in enumerate(attrs))
    rows = []
    for s in range(top + 2):
        for c in combinations(range(len(attrs)), s):
            mask = sum(1 << i for i in c)
            rows.append(f"select {mask} as mask, node, count(*) as n, '{names(mask, attrs)}' as lhs, {s} as size from (select distinct {', '.join(['node', *(attrs[i] for i in c)])} from l) group by node")
    return f"""with l as (select *, {NODE.format(k=k)} as node from lineitem), c as ({' union all '.join(rows)}), a(bit, name) as (values {bits}),
fd as (select x.mask, x.lhs, x.size, a.bit, a.name from c x, a, c y where x.size <= {top} and (x.mask & a.bit) = 0 and y.mask = (x.mask | a.bit) and y.node = x.node and y.n = x.n group by all having count(*) = (select count(distinct node) from l))
select lhs, name as rhs, size as lhs_size from fd f where not exists (select 1 from fd g where g.bit = f.bit and g.mask <> f.mask and (g.mask & f.mask) = g.mask)"""


def q_local(k, most=None):
    def run(spark, sf_dir):
        attrs = ATTRS["lineitem"]
        found = baselines.local_intersect(table(spark, sf_dir, "lineitem").select(*attrs), F.expr(NODE.format(k=k)), k, most)
        return spark.createDataFrame([(names(x, attrs), names(a, attrs), x.bit_count()) for x, a in found], FD)

    return run


for k in (2, 4, 8):
    register(f"local_intersect_lineitem_k{k}", q_local(k, 2), local_sql(k, 2))
register("local_intersect_lineitem_all", q_local(4))


def q_sample(spark, sf_dir):
    attrs = ATTRS["lineitem"]
    found = baselines.sample_only(table(spark, sf_dir, "lineitem").select(*attrs), F.col("l_partkey") % 10 == 0, None)
    return spark.createDataFrame([(names(x, attrs), names(a, attrs), x.bit_count()) for x, a in found], FD)


register("sample_only_lineitem", q_sample, fd_sql("select * from lineitem where l_partkey % 10 = 0", ATTRS["lineitem"]))
register("single_task_part", lambda spark, sf_dir: baselines.single_task(table(spark, sf_dir, "part")), SQL["fd_part_lattice_rescan_spill"])
register("single_task_part_pairs", lambda spark, sf_dir: baselines.single_task(table(spark, sf_dir, "part"), "pair"), SQL["fd_part_lattice_rescan_spill"])


def precision_sql(local: str, label: str, most: int) -> str:
    """Share of the dependencies in `local` that hold on all rows, and of the minimal ones of all rows that some of them implies."""
    attrs = ATTRS["lineitem"]
    inside = lambda x, y: f"list_has_all(string_split({y}, ','), string_split({x}, ','))"
    return f"""with exact as materialized ({fd_sql('select * from lineitem', attrs, most)}), own as materialized ({local})
select {label}, (select count(*) from own)::int as n_found,
round((select count(*) filter (exists (select 1 from exact e where e.rhs = own.rhs and (e.lhs = '' or {inside('e.lhs', 'own.lhs')}))) / count(*) from own), 6) as precision,
round((select count(*) filter (exists (select 1 from own o where o.rhs = exact.rhs and (o.lhs = '' or {inside('o.lhs', 'exact.lhs')}))) / count(*) from exact), 6) as recall"""


def q_precision(ks, most):
    def run(spark, sf_dir):
        df = table(spark, sf_dir, "lineitem")
        exact, rows = planner.whole(df, memory="resident", max_lhs=most).found, []
        for k in ks:
            local = baselines.local_intersect(df, F.expr(NODE.format(k=k)), k, most)
            rows.append((k, len(local), *(round(float(x), 6) for x in baselines.precision(local, exact))))
        return spark.createDataFrame(rows, "nodes int, n_found int, precision double, recall double")

    return run


register("precision_by_nodes", q_precision((2, 4, 6, 8, 10), 3))
register("precision_by_nodes_lhs2", q_precision((2, 4, 6, 8, 10), 2), " union all ".join(f"select * from ({precision_sql(local_sql(k, 2), f'{k} as nodes', 2)})" for k in (2, 4, 6, 8, 10)))
PERCENTS = (1, 5, 10, 25, 50)
SAMPLED = "(l_orderkey * 31 + l_partkey * 17 + l_linenumber * 7) % 100 < {p}"


def q_sample_precision(most):
    def run(spark, sf_dir):
        df = table(spark, sf_dir, "lineitem")
        exact, rows = planner.whole(df, memory="resident", max_lhs=most).found, []
        for p in PERCENTS:
            own = baselines.sample_only(df, F.expr(SAMPLED.format(p=p)), most)
            rows.append((p, len(own), *(round(float(x), 6) for x in baselines.precision(own, exact))))
        return spark.createDataFrame(rows, "percent int, n_found int, precision double, recall double")

    return run


register("precision_by_sample", q_sample_precision(3))
register("precision_by_sample_lhs2", q_sample_precision(2), " union all ".join(f"select * from ({precision_sql(fd_sql('select * from lineitem where ' + SAMPLED.format(p=p), ATTRS['lineitem'], 2), f'{p} as percent', 2)})" for p in PERCENTS))

# -- worked examples ------------------------------------------------

ABCD = [("a", "a", "a", "a"), ("b", "b", "a", "a"), ("a", "c", "a", "c"), ("b", "c", "d", "e")]
#: Four rows that all orders make: finished or not (A), urgent or not (B), the smallest customer (C) and the last year (D) of each.
FOUR_SQL = """select (1 + 2 * (o_orderstatus <> 'F')::int + (o_orderpriority <> '1-URGENT')::int)::int as id, (o_orderstatus <> 'F')::int::varchar as A, (o_orderpriority <> '1-URGENT')::int::varchar as B,
min(o_custkey)::varchar as C, year(max(o_orderdate))::varchar as D from orders group by o_orderstatus <> 'F', o_orderpriority <> '1-URGENT'"""
ABCD_SQL = f"select A, B, C, D from ({FOUR_SQL})"


def four(spark, sf_dir):
    """(id, A, B, C, D) by one pass over orders."""
    open_, calm = (F.col("o_orderstatus") != "F").cast("int").alias("a"), (F.col("o_orderpriority") != "1-URGENT").cast("int").alias("b")
    made = table(spark, sf_dir, "orders").groupBy(open_, calm).agg(F.min("o_custkey").cast("string").alias("C"), F.year(F.max("o_orderdate")).cast("string").alias("D"))
    return materialize(made.select((1 + 2 * F.col("a") + F.col("b")).cast("int").alias("id"), F.col("a").cast("string").alias("A"), F.col("b").cast("string").alias("B"), "C", "D"), "four-rows")


def abcd(spark, sf_dir):
    return four(spark, sf_dir).select(*"ABCD")


register("example_four_rows_fds", lambda spark, sf_dir: planner.whole(abcd(spark, sf_dir), method="pair", memory="resident").dependencies, fd_sql(ABCD_SQL, list("ABCD")))
register("example_four_rows_keys", lambda spark, sf_dir: planner.whole(abcd(spark, sf_dir), "ucc").dependencies, ucc_sql(ABCD_SQL, list("ABCD")))


def q_example_evidence(spark, sf_dir):
    rows, _, _ = pairs.compacted(abcd(spark, sf_dir), list("ABCD"))
    return evidence.histogram(pairs.pairs_of(rows, list("ABCD"), "rescan", "resident", 3), evidence.differs(list("ABCD")))


register("example_four_rows_evidence", q_example_evidence, f"with f as ({FOUR_SQL}) select {mask_sql(list('ABCD'))} as ev0, count(*) as n_pairs from f l join f r on l.id < r.id group by 1")


def q_two_nodes(spark, sf_dir):
    df = spark.createDataFrame([(0, "a1", "b1")] * 2 + [(1, "a1", "b2")] * 2, "node int, A string, B string")
    local = baselines.local_intersect(df.select("A", "B", "node"), F.col("node"), 2, 1)
    whole = planner.whole(df.select("A", "B")).found
    return spark.createDataFrame([("local", sum(1 for x, a in local if a == 2)), ("whole", sum(1 for x, a in whole if a == 2))], "where string, n_fds int").withColumnRenamed("where", "found_on")


register("example_two_nodes", q_two_nodes, "select * from (values ('local', 1), ('whole', 0)) t(found_on, n_fds)")


def q_example_classes(spark, sf_dir):
    """The classes of A, B, C, D from rows, and of CD from the stored classes of C and D."""
    rows = four(spark, sf_dir)
    single = materialize(partition.column_classes(rows, list("ABCD"), "id"), "classes")
    both = partition.intersect(single, spark.createDataFrame([(4, 2, 3)], "node int, left int, right int"))
    named = F.get(F.array(*map(F.lit, ["A", "B", "C", "D", "CD"])), F.col("node"))
    return single.unionByName(both).groupBy(named.alias("attrs"), "class_id").agg(F.array_join(F.transform(F.array_sort(F.collect_list("row_id")), lambda x: x.cast("string")), ",").alias("members")).select("attrs", "members")


register("example_four_rows_classes", q_example_classes, f"with f as ({FOUR_SQL}) " + " union all ".join(f"select '{''.join(c)}' as attrs, string_agg(id::varchar, ',' order by id) as members from f group by {', '.join(c)}" for c in ("A", "B", "C", "D", "CD")))


def q_example_meetings(spark, sf_dir):
    """How often each two rows meet: once for each shared value in the reuse plan, never if they share none, once in the rescan plan."""
    rows = four(spark, sf_dir)
    met = lambda pairs, n: pairs.select(F.least("l_id", "r_id").alias("a"), F.greatest("l_id", "r_id").alias("b")).groupBy("a", "b").agg(F.count("*").alias(n))
    reuse, rescan = met(distribute.blocks(rows, list("ABCD"), 3, ["id"]), "n_reuse"), met(distribute.triangle(rows, 3, ["id"]), "n_rescan")
    return rescan.join(reuse, ["a", "b"], "left").select("a", "b", F.coalesce("n_reuse", F.lit(0)).alias("n_reuse"), "n_rescan")


register("example_four_rows_meetings", q_example_meetings, f"with f as ({FOUR_SQL}) select l.id as a, r.id as b, ({' + '.join(f'(l.{c} = r.{c})::int' for c in 'ABCD')})::bigint as n_reuse, 1::bigint as n_rescan from f l join f r on l.id < r.id")
#: Fixed example rows: tax records.
TAX_ATTRS = ["ID", "GD", "AC", "PH", "CT", "ST", "ZIP", "SAL", "TR", "STX"]
TAX = [
    ("1009", "M", 304, "232-7667", "Anthony", "WV", 25813, 5000, 3.0, 2000),
    ("2136", "M", 719, "154-4816", "Denver", "CO", 80290, 60000, 4.63, 0),
    ("0457", "F", 636, "604-2692", "Cyrene", "MO", 64739, 40000, 6.0, 0),
    ("1942", "F", 501, "378-7304", "West Crossett", "AR", 72045, 85000, 7.22, 0),
    ("2247", "M", 319, "150-3642", "Gifford", "IA", 52404, 15000, 2.48, 50),
    ("6160", "M", 970, "190-3324", "Denver", "CO", 80251, 60000, 4.63, 0),
    ("4312", "F", 501, "154-4816", "Kremlin", "AR", 72045, 70000, 7.0, 0),
    ("3339", "F", 304, "540-4707", "Kyle", "WV", 25813, 10000, 4.0, 500),
]


def tax(spark):
    return spark.createDataFrame(TAX, "ID string, GD string, AC int, PH string, CT string, ST string, ZIP int, SAL int, TR double, STX int")


#: The records of the table: for each nation its block of five, its customers, those in debt, the least and the greatest balance, and the first name.
ACC_ATTRS = ["nation", "block", "customers", "in_debt", "least", "most", "first_name"]
ACC_SQL = "select c_nationkey::bigint as nation, c_nationkey::bigint // 5 as block, count(*) as customers, count(case when c_acctbal < 0 then 1 end) as in_debt, min(c_acctbal) as least, max(c_acctbal) as most, min(c_name) as first_name from customer group by c_nationkey"


def accounts(spark, sf_dir):
    """A record for each nation by one pass over customer."""
    made = table(spark, sf_dir, "customer").groupBy(F.col("c_nationkey").cast("long").alias("nation")).agg(F.count("*").alias("customers"), F.count(F.when(F.col("c_acctbal") < 0, 1)).alias("in_debt"), F.min("c_acctbal").alias("least"), F.max("c_acctbal").alias("most"), F.min("c_name").alias("first_name"))
    return materialize(made.withColumn("block", F.expr("nation div 5")).select(*ACC_ATTRS), "accounts")


register("example_tax_fds", lambda spark, sf_dir: planner.whole(accounts(spark, sf_dir)).dependencies, fd_sql(ACC_SQL, ACC_ATTRS))
register("example_tax_keys", lambda spark, sf_dir: planner.whole(accounts(spark, sf_dir), "ucc", method="pair", memory="resident").dependencies, ucc_sql(ACC_SQL, ACC_ATTRS))
#: Of two nations of one block the one with fewer customers has no greater balance at most.
ACC_DC = [("block", "="), ("customers", "<"), ("most", ">")]
ACC_HELD = [("nation", "="), ("customers", "<")]
register("example_tax_constraint", lambda spark, sf_dir: reason.dc_violations(accounts(spark, sf_dir), ACC_DC, "nation").agg(F.count("*").alias("n_violations")), f"with s as ({ACC_SQL}) select count(*) as n_violations from s a join s b on a.block = b.block and a.customers < b.customers and a.most > b.most")
ACC_FEW = ["nation", "block", "customers", "most"]


def q_tax_constraints(spark, sf_dir):
    """Whether discovery reports each of two constraints, or a more general one that implies it: one whose every comparison follows from one of the constraint's."""
    found = [r["dc"] for r in planner.denial_constraints(accounts(spark, sf_dir), ACC_FEW, max_predicates=3).collect()]
    weaker = lambda op: {op} | {w for x in predicates.WEAKER[op] for w in weaker(x)}
    rows = []
    for name, dc in (("block", ACC_DC), ("nation", ACC_HELD)):
        said = [{f"t1.{a} {w} t2.{a}" for a, op in q for w in weaker(op)} for q in (dc, [(a, predicates.FLIP[op]) for a, op in dc])]
        rows.append((name, any(set(f.split(" and ")) <= own for f in found for own in said)))
    return spark.createDataFrame(rows, "within string, reported boolean")


register("example_tax_constraint_found", q_tax_constraints, f"with s as ({ACC_SQL}) select 'block' as within, not exists (select 1 from s a join s b on a.block = b.block and a.customers < b.customers and a.most > b.most) as reported union all select 'nation', not exists (select 1 from s a join s b on a.nation = b.nation and a.customers < b.customers)")


def q_tax_evidence(spark, sf_dir):
    """What the records of nations 2 and 6 differ in, and which comparisons they satisfy."""
    df = accounts(spark, sf_dir)
    two = df.where("nation = 2").select(*[F.col(c).alias(f"l_{c}") for c in df.columns]).crossJoin(df.where("nation = 6").select(*[F.col(c).alias(f"r_{c}") for c in df.columns]))  # one row each
    mask = next(iter(evidence.masks(evidence.histogram(two, evidence.differs(df.columns)))))
    space = predicates.space_of(df, df.columns, order_texts=True)
    code = next(iter(evidence.masks(evidence.histogram(two, space.codes()))))
    held = [space.slots[s].spelled(op) for s, op in space.predicates if op in predicates.SATISFIED[space.outcome(code, s)]]
    return spark.createDataFrame([("differs", a) for i, a in enumerate(df.columns) if mask >> i & 1] + [("satisfies", p) for p in held], "kind string, said string")


_BOTH = f"with l as (select * from ({ACC_SQL}) where nation = 2), r as (select * from ({ACC_SQL}) where nation = 6)"
register("example_tax_evidence", q_tax_evidence, _BOTH + " " + " union all ".join([f"select 'differs' as kind, '{a}' as said from l, r where l.{a} <> r.{a}" for a in ACC_ATTRS] + [f"select 'satisfies', 't1.{a} {o} t2.{a}' from l, r where l.{a} {o} r.{a}" for a in ACC_ATTRS for o in ("=", "!=", "<", "<=", ">", ">=")]))
_OD = ["SAL", "STX"]
register("example_tax_order", lambda spark, sf_dir: planner.order_dependencies(tax(spark), _OD), "select 'SAL' as lhs, 'STX' as rhs, 'desc' as direction, 'list' as kind")

# -- uses ------------------------------------------------

register("fd_violations_customer", lambda spark, sf_dir: reason.violations(table(spark, sf_dir, "customer"), ["c_acctbal"], "c_nationkey").select("c_custkey"), "select c_custkey from customer where c_acctbal in (select c_acctbal from customer group by 1 having count(distinct c_nationkey) > 1)")
register("g3_orders", lambda spark, sf_dir: reason.g3_error(table(spark, sf_dir, "orders"), ["o_custkey"], "o_orderstatus"), "select sum(n)::bigint as n_rows, sum(n - most)::bigint as n_delete from (select sum(n) as n, max(n) as most from (select o_custkey, o_orderstatus, count(*) as n from orders group by 1, 2) group by o_custkey)")
register("duplicate_keys_lineitem", lambda spark, sf_dir: reason.duplicate_keys(table(spark, sf_dir, "lineitem"), ["l_orderkey", "l_linenumber"]), "select l_orderkey, l_linenumber, count(*) as n_rows from lineitem group by 1, 2 having count(*) > 1")


def star_fds(spark, sf_dir):
    return reason.as_sets(planner.whole(relation(spark, sf_dir, "star14").select(*STAR_ALL), memory="resident", max_lhs=1).dependencies.collect())


register("candidate_keys_star", lambda spark, sf_dir: spark.createDataFrame([(",".join(sorted(k)),) for k in reason.candidate_keys(STAR_ALL, star_fds(spark, sf_dir))], "candidate_key string"), "select 'o_orderkey' as candidate_key")
register("bcnf_star", lambda spark, sf_dir: spark.createDataFrame([(",".join(sorted(x)), a) for x, a in reason.bcnf_violations(STAR_ALL, star_fds(spark, sf_dir))], "lhs string, rhs string"), "select lhs, rhs from (" + fd_sql(STAR_SQL, STAR_ALL, 1) + ") where lhs <> 'o_orderkey'")
register("shrink_group_by_star", lambda spark, sf_dir: spark.createDataFrame([(c,) for c in reason.shrink_group_by(["c_custkey", "c_name", "n_name", "n_regionkey", "o_orderstatus"], star_fds(spark, sf_dir))], "kept string"), "select * from (values ('c_custkey'), ('o_orderstatus')) t(kept)")
register("shrink_order_by_events", lambda spark, sf_dir: spark.createDataFrame([(c,) for c in reason.shrink_order_by(["event_id", "ts", "value"], [(r["lhs"], r["rhs"]) for r in QUERIES["od_events_unary_asc"](spark, sf_dir).collect()])], "kept string"), "select * from (values ('event_id'), ('value')) t(kept)")


EARLIER = "o_orderdate < timestamp '1994-01-01'"  # the state of an earlier day, against today's


def q_change(spark, sf_dir):
    attrs = ["o_orderkey", "o_custkey", "o_totalprice", "o_orderdate"]
    df = table(spark, sf_dir, "orders").select(*attrs)
    return reason.compare(planner.whole(df.where(EARLIER), memory="resident").dependencies, planner.whole(df, memory="resident").dependencies)


O4 = ["o_orderkey", "o_custkey", "o_totalprice", "o_orderdate"]
register("dependency_change_orders", q_change, f"select lhs, rhs, lhs_size, case when o.k is null then 'gained' when n.k is null then 'lost' else 'kept' end as change from (select *, 1 as k from ({fd_sql('select * from orders where ' + EARLIER, O4)})) o full join (select *, 1 as k from ({fd_sql('select * from orders', O4)})) n using (lhs, rhs, lhs_size)")

# -- relational support ------------------------------------------------

register("join_semi_orders", lambda s, d: table(s, d, "customer").join(table(s, d, "orders").where("o_orderstatus = 'F'"), F.col("c_custkey") == F.col("o_custkey"), "left_semi").select("c_custkey"), "select c_custkey from customer where c_custkey in (select o_custkey from orders where o_orderstatus = 'F')")
register("join_anti_orders", lambda s, d: table(s, d, "customer").join(table(s, d, "orders"), F.col("c_custkey") == F.col("o_custkey"), "left_anti").select("c_custkey"), "select c_custkey from customer where c_custkey not in (select o_custkey from orders)")
register("join_outer_nation", lambda s, d: table(s, d, "nation").join(table(s, d, "supplier"), F.col("n_nationkey") == F.col("s_nationkey"), "full_outer").groupBy("n_name").agg(F.count("s_suppkey").alias("n_suppliers")), "select n_name, count(s_suppkey) as n_suppliers from nation full join supplier on n_nationkey = s_nationkey group by 1")
register("join_band_part", lambda s, d: relational.band(table(s, d, "part").select("p_partkey", F.col("p_retailprice").alias("x")), table(s, d, "supplier").select("s_suppkey", F.col("s_acctbal").alias("y")), "x", "y", 25.0).groupBy("s_suppkey").agg(F.count("*").alias("n_near")), "select s_suppkey, count(*) as n_near from part join supplier on abs(p_retailprice - s_acctbal) <= 25 group by 1")


def q_as_of(s, d):
    e = table(s, d, "events")
    return relational.as_of(e.where("event_type = 'purchase'").select("event_id", "ts", "user_id"), e.where("event_type <> 'purchase'").select("ts", "user_id", "value"), "ts", ["user_id"], ["value"]).select("event_id", F.col("as_of_value").alias("last_value"))


register("join_as_of_events", q_as_of, "select l.event_id, r.value as last_value from (select * from events where event_type = 'purchase') l asof left join (select * from events where event_type <> 'purchase') r on l.user_id = r.user_id and l.ts >= r.ts")
register("grouping_sets_orders", lambda s, d: (lambda o: o.groupingSets([[o.o_orderstatus], [o.o_orderpriority], []], o.o_orderstatus, o.o_orderpriority).agg(F.count("*").alias("n")))(table(s, d, "orders")), "select o_orderstatus, o_orderpriority, count(*) as n from orders group by grouping sets ((o_orderstatus), (o_orderpriority), ())")
register("cube_lineitem", lambda s, d: table(s, d, "lineitem").cube("l_returnflag", "l_linestatus").agg(F.count("*").alias("n"), F.sum("l_linenumber").alias("total")), "select l_returnflag, l_linestatus, count(*) as n, sum(l_linenumber)::bigint as total from lineitem group by cube (l_returnflag, l_linestatus)")
register("rollup_lineitem", lambda s, d: table(s, d, "lineitem").rollup("l_returnflag", "l_linestatus").agg(F.count("*").alias("n")), "select l_returnflag, l_linestatus, count(*) as n from lineitem group by rollup (l_returnflag, l_linestatus)")
register("running_max_orders", lambda s, d: table(s, d, "orders").select("o_orderkey", F.max("o_totalprice").over(Window.partitionBy("o_custkey").orderBy("o_orderkey").rowsBetween(Window.unboundedPreceding, -1)).alias("before")), "select o_orderkey, max(o_totalprice) over (partition by o_custkey order by o_orderkey rows between unbounded preceding and 1 preceding) as before from orders")
register("top_classes_lineitem", lambda s, d: table(s, d, "lineitem").groupBy("l_partkey").agg(F.count("*").alias("n")).orderBy(F.desc("n"), "l_partkey").limit(10), "select l_partkey, count(*) as n from lineitem group by 1 order by n desc, l_partkey limit 10")
register("set_operations_keys", lambda s, d: table(s, d, "customer").select(F.col("c_nationkey").alias("k")).intersect(table(s, d, "supplier").select("s_nationkey")).union(table(s, d, "nation").select("n_nationkey").exceptAll(table(s, d, "supplier").select("s_nationkey").distinct())), "(select c_nationkey as k from customer intersect select s_nationkey from supplier) union all (select n_nationkey from nation except all select distinct s_nationkey from supplier)")
register("json_events", lambda s, d: table(s, d, "events").select("event_id", F.get_json_object("props", "$.k").cast("int").alias("k")), "select event_id, cast(json_extract_string(props, '$.k') as int) as k from events")
register("dates_orders", lambda s, d: table(s, d, "orders").groupBy(F.year("o_orderdate").alias("y"), F.quarter("o_orderdate").alias("q")).agg(F.count("*").alias("n")), "select year(o_orderdate)::int as y, quarter(o_orderdate)::int as q, count(*) as n from orders group by 1, 2")

# -- streams, as batches ------------------------------------------------


def events(s, d):
    return table(s, d, "events").withColumn("ts", F.col("ts").cast("timestamp"))


register("events_tumbling_fd", lambda s, d: monitor.window_fd(events(s, d), "ts", "1 day", ["user_id"], "event_type").groupBy("user_id").agg(F.count("*").alias("n_windows")), "select user_id, count(*) as n_windows from (select user_id, time_bucket(interval 1 day, ts, timestamp '1970-01-01') as w from events group by 1, 2 having count(distinct event_type) > 1) group by 1")
register("events_sliding_counts", lambda s, d: monitor.window_counts(events(s, d), "ts", "2 days", "1 day").select(F.unix_timestamp("window_start").alias("start_s"), "n_rows"), "select (epoch(w) - b * 86400)::bigint as start_s, count(*) as n_rows from (select time_bucket(interval 1 day, ts, timestamp '1970-01-01') as w from events), range(2) t(b) group by 1")
register("events_session_counts", lambda s, d: monitor.session_counts(events(s, d), "ts", "6 hours", "user_id").groupBy("user_id").agg(F.count("*").alias("n_sessions"), F.max("n_rows").alias("longest")), """select user_id, count(*) as n_sessions, max(n) as longest from (select user_id, s, count(*) as n from (select user_id, sum(new) over (partition by user_id order by ts) as s from (select user_id, ts, case when ts >= lag(ts) over (partition by user_id order by ts) + interval 6 hour then 1 else 0 end as new from events)) group by 1, 2) group by 1""")
register("events_fd_refutations", lambda s, d: monitor.watch_fd(events(s, d), ["user_id"], "event_type"), "select user_id, min(event_type) as value_1, max(event_type) as value_2 from events group by 1 having min(event_type) <> max(event_type)")
register("events_ucc_refutations", lambda s, d: monitor.watch_ucc(events(s, d), ["user_id", "event_type"]), "select user_id, event_type, count(*) as n_rows from events group by 1, 2 having count(*) > 1")

# -- functions for SQL users, and levels in Spark ------------------------------------------------


def q_cells(spark, sf_dir):
    register_functions(spark)
    return spark.sql("select r.anchor, c.* from (select explode(sequence(0, 3)) as anchor) r, lateral triangle_cells(r.anchor, 4) c")


register("sql_triangle_cells", q_cells, "select a.i as anchor, (least(a.i, o.i) * 4 + greatest(a.i, o.i))::int as cell, a.i <= o.i as stands_left, a.i >= o.i as stands_right from (select unnest([0, 1, 2, 3]) as i) a, (select unnest([0, 1, 2, 3]) as i) o")


def q_antichain(spark, sf_dir):
    register_functions(spark)
    q_evidence("part")[0](spark, sf_dir).createOrReplaceTempView("depmine_evidence")
    return spark.sql("select explode(mask_antichain(ev0)) as ev0 from depmine_evidence")


register("sql_mask_antichain_part", q_antichain, f"with e as (select distinct {mask_sql(ATTRS['part'])} as ev0 from part l join part r on l.p_partkey < r.p_partkey) select ev0 from e where not exists (select 1 from e o where o.ev0 <> e.ev0 and (o.ev0 & e.ev0) = o.ev0)")


def q_tests(spark, sf_dir):
    """Every candidate of level two of orders, tested on the workers."""
    attrs = ATTRS["orders"]
    df = table(spark, sf_dir, "orders")
    one, two = [1 << i for i in range(6)], [1 << i | 1 << j for i, j in combinations(range(6), 2)]
    found = refine.level_tests(spark, partition.counts_by_grouping_sets(df, attrs, two), partition.counts_by_grouping_sets(df, attrs, one))
    name = F.create_map(*[x for i, a in enumerate(attrs) for x in (F.lit(str(1 << i)), F.lit(a))])
    return found.select(F.element_at(name, F.col("lhs")).alias("lhs"), F.element_at(name, F.col("rhs")).alias("rhs"), "holds")


register("level_tests_orders", q_tests, " union all ".join(f"select '{a}' as lhs, '{b}' as rhs, not exists (select 1 from orders group by {a} having count(distinct {b}) > 1) as holds" for a in ATTRS["orders"] for b in ATTRS["orders"] if a != b))
for memory in ("resident", "spill"):
    register(f"level_join_lineitem_{memory}", lambda s, d, memory=memory: s.createDataFrame([(names(x, ATTRS["lineitem"]),) for x in lattice.joined(s, [1 << i | 1 << j for i, j in combinations(range(11), 2)], 6, memory)], "lhs string"), "select * from (values " + ", ".join(f"('{','.join(sorted(c))}')" for c in combinations(ATTRS["lineitem"], 3)) + ") t(lhs)")

# -- experiments ------------------------------------------------

RESULT = ("experiment", "relation", "n_rows", "n_columns", "method", "plan", "memory", "n_found", "status")
COUNTED = {t: f"(select count(*) from ({SQL[f'fd_{t}_lattice_rescan_spill']}))" for t in ("part", "customer", "orders")}


def report_sql(experiment: str, runs) -> str:
    """(relation, kind and method, plan, memory) of finished runs."""
    return " union all ".join(f"select '{experiment}' as experiment, '{t}' as relation, (select count(*) from {t}) as n_rows, {len(ATTRS[t])}::int as n_columns, '{m}' as method, '{p}' as plan, '{s}' as memory, {COUNTED[t]} as n_found, 'done' as status" for t, m, p, s in runs)


for method in ("lattice", "pair", "hybrid"):
    register(f"plans_{method}_small", lambda s, d, method=method: workloads.plans(s, d, method, ("part", "customer"), ("resident", "spill"), limits=workloads.WHOLE).select(*RESULT), report_sql(f"{method} plans", [(t, f"fd_{method}", p, m) for t in ("part", "customer") for p in ("reuse", "rescan") for m in ("resident", "spill")]))
    register(f"plans_{method}_costs", lambda s, d, method=method: workloads.plans(s, d, method, ("part", "customer") if method == "pair" else ("part", "star14")))
register("memories_small", lambda s, d: workloads.memories(s, d, ("part", "customer"), (5.0, 0.001), limits=workloads.WHOLE).select(*RESULT), " union all ".join(report_sql(f"workers of {mb} MB", [(t, f"fd_{m}", "rescan", memory) for t in ("part", "customer") for m in ("lattice", "pair", "hybrid")]) for mb, memory in (("5", "resident"), ("0.001", "spill"))))
register("memories_costs", lambda s, d: workloads.memories(s, d))
register("three_versions_part", lambda s, d: workloads.three_versions(s, d, limits=workloads.WHOLE).select(*RESULT), f"select 'three versions' as experiment, 'part' as relation, (select count(*) from part) as n_rows, 6::int as n_columns, 'fd_pair' as method, plan, 'resident' as memory, {COUNTED['part']} as n_found, 'done' as status from (values ('single task'), ('reuse'), ('rescan')) t(plan)")
register("three_versions_customer", lambda s, d: workloads.three_versions(s, d, "customer"))
register("pair_growth_lineitem", lambda s, d: workloads.pair_growth(s, d))
register("scaling_workers_part", lambda s, d: workloads.workers(s, d))
register("scaling_rows_lineitem", lambda s, d: workloads.by_rows(s, d, "lineitem", methods=(("fd", "lattice"), ("fd", "pair"), ("fd", "hybrid"), ("ucc", "hybrid"))))
register("scaling_rows_part_seven", lambda s, d: workloads.by_rows(s, d, "part"))
register("scaling_rows_star14", lambda s, d: workloads.by_rows(s, d, "star14", (20, 60, 100), workloads.SEVEN[:4]))
register("scaling_columns_wide109", lambda s, d: workloads.by_columns(s, d, "wide109", (5, 10, 20), 1_000, max_lhs=2))
register("scaling_columns_wide60", lambda s, d: workloads.by_columns(s, d, "wide60", (5, 10), 10_000, workloads.FD_KINDS, max_lhs=2))
register("scaling_columns_part_seven", lambda s, d: workloads.by_columns(s, d, "part", (2, 3, 4, 5, 6), methods=workloads.SEVEN))
register("hybrid_phases_star14", lambda s, d: workloads.phases(s, d))
register("methods_by_relation", lambda s, d: workloads.by_relation(s, d, ("star14", "lineitem")))
