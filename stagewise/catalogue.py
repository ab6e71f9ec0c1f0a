"""All queries of the engine, with the SQL that gives the same rows."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from stagewise import study
from stagewise.functions import hpfunc as H
from stagewise.functions import space
from stagewise.operators import experiments as X
from stagewise.operators import measures as M
from stagewise.operators import simulate, training, tuners
from stagewise.plans import forest, plan, schedule
from stagewise.plans import trials as T
from stagewise.sources import adapters as A
from stagewise.store import PlanStore, Scratch
from stagewise.streaming import reports
from stagewise.study import Study

_Q: dict = {}
_SQL: dict[str, str] = {}
HIGH = [["0"], ["0", "1"], [str(i) for i in range(4)], [str(i) for i in range(8)]]


def _register(name: str, sql: str | None = None):
    def keep(f):
        _Q[name] = f
        if sql is not None:
            _SQL[name] = sql
        return f

    return keep


def queries() -> dict:
    return dict(_Q)


def oracle_sql() -> dict[str, str]:
    return dict(_SQL)


# --- pieces and segments ------------------------------------------------------------------

PIECES = {
    "orders": "select 'all' as study, o_custkey as trial, row_number() over (partition by o_custkey order by o_orderdate, o_orderkey) as ord, substr(o_orderpriority, 1, 1) as cfg, case o_orderstatus when 'F' then 10 when 'O' then 20 else 30 end as steps from orders",
    "lineitem": "select 'all' as study, l_orderkey as trial, row_number() over (partition by l_orderkey order by l_linenumber, l_partkey, l_suppkey, l_shipdate, l_quantity, l_extendedprice, l_returnflag, l_linestatus) as ord, l_returnflag || '|' || l_linestatus as cfg, cast(l_quantity as bigint) as steps from lineitem",
    "events": "select 'all' as study, user_id * 100000 + date_diff('day', date '1970-01-01', cast(ts as date)) as trial, row_number() over (partition by user_id, cast(ts as date) order by ts, event_id) as ord, event_type as cfg, 10 as steps from events",
    "conversations": "select 'all' as study, conv_id as trial, row_number() over (partition by conv_id order by turn, role) as ord, role as cfg, 10 as steps from conversations",
}
PIECES["by_segment"] = f"select c_mktsegment as study, trial, ord, cfg, steps from ({PIECES['orders']}) p join customer on trial = c_custkey"
PIECES["high"] = f"select cast(c_nationkey as varchar) as study, o_custkey as trial, row_number() over (partition by o_custkey order by o_orderdate, o_orderkey) as ord, o_orderstatus as cfg, case o_orderstatus when 'F' then 10 when 'O' then 20 else 30 end as steps from orders join customer on o_custkey = c_custkey where c_nationkey < 8"
PIECES["nations"] = PIECES["high"].removesuffix(" where c_nationkey < 8")
PIECES["low"] = PIECES["high"].replace("o_orderstatus as cfg", "substr(o_orderpriority, 1, 1) || o_orderstatus as cfg")
_LR, _LAST = "case o_orderstatus when 'F' then '0.1' when 'O' then '0.05' else '0.01' end", "case when o_orderpriority like '1%' then 150 else 100 end"
PIECES |= {f"block{n}": f"select coalesce(cast(o_custkey // {n} as varchar), '-') as study, o_custkey as trial, row_number() over (partition by o_custkey order by o_orderdate, o_orderkey) as ord, {_LR} as cfg, {_LAST} as steps from orders" for n in (4, 5)}
PIECES["pairs"] = "select coalesce(cast(o_custkey as varchar), '-') as study, o_orderkey as trial, ord, case when ord = 0 then case o_orderstatus when 'F' then '0.1' when 'O' then '0.01' else '0.05' end else case substr(o_orderpriority, 1, 1) when '1' then '0.1' when '2' then '0.05' when '3' then '0.01' when '4' then '0.005' else '0.001' end end as cfg, 100 as steps from (select *, unnest([0, 1]) as ord from orders)"
PIECES["years"] = "select 'all' as study, o_custkey * 10000 + year(o_orderdate) as trial, row_number() over (partition by o_custkey, year(o_orderdate) order by o_orderdate, o_orderkey) as ord, 'H' || substr(o_orderpriority, 1, 1) as cfg, 10 + 5 * (o_orderkey % 3) as steps from orders"


def seg_sql(kind: str) -> str:
    """with-clause up to ``seg``(study, trial, k, start, end_, cfg, path, parent) in the oracle's SQL."""
    return f"""with pc as ({PIECES[kind]}),
fl as (select *, case when lag(1) over w is null or lag(cfg) over w is distinct from cfg then 1 else 0 end as f from pc window w as (partition by study, trial order by ord)),
il as (select *, sum(f) over (partition by study, trial order by ord rows unbounded preceding) as island from fl),
g as (select study, trial, island - 1 as k, min(cfg) as cfg, sum(steps) as steps from il group by study, trial, island),
pr as (select *, coalesce(sum(steps) over (partition by study, trial order by k rows between unbounded preceding and 1 preceding), 0) as start from g),
pt as (select *, list(cast(cast(start as bigint) as varchar) || '|' || case when cfg is null then '-' else length(cfg) || ':' || cfg end) over (partition by study, trial order by k rows unbounded preceding) as parts from pr),
pa as (select *, list_reduce(list_prepend('', parts), lambda a, x: substr(sha256(a || '|' || x), 1, 32)) as path from pt),
seg as (select study, trial, cast(k as bigint) as k, cast(start as bigint) as start, cast(start + steps as bigint) as end_, cfg, path, lag(path) over (partition by study, trial order by k) as parent from pa)
"""


def seg(spark: SparkSession, d: str, kind: str) -> DataFrame:
    if kind in ("orders", "lineitem", "events", "conversations"):
        return T.canonical(getattr(A, kind)(spark, d))
    if kind in ("block4", "block5"):
        return T.canonical(A.blocks(spark, d, int(kind[-1])))
    if kind in ("pairs", "years"):
        return T.canonical(getattr(A, kind)(spark, d))
    value = {"by_segment": "priority", "high": "status", "nations": "status", "low": "both"}[kind]
    p = A.with_customer(A.orders(spark, d, value), spark, d, "c_mktsegment" if kind == "by_segment" else "c_nationkey")
    return T.canonical(p.where("cast(study as int) < 8") if kind in ("high", "low") else p)


_RATE = "select cast(sum(r) as bigint) as trials, cast(sum(t) as bigint) as total_steps, cast(sum(u) as bigint) as unique_steps, count(*) as nodes, round(sum(t) / sum(u), 6) as rate from (select path, sum(end_ - start) as t, max(end_) - min(start) as u, count(*) filter (where k = 0) as r from seg group by path)"
for _kind in ("orders", "lineitem", "events", "conversations"):
    _register(f"merge_{_kind}", seg_sql(_kind) + _RATE)(lambda s, d, k=_kind: M.merge_rate(seg(s, d, k)))
_register("merge_by_segment", seg_sql("by_segment") + _RATE.replace("select cast(sum(r)", "select study, cast(sum(r)").replace("(select path", "(select study, path").replace("group by path)", "group by study, path) group by study"))(
    lambda s, d: M.merge_rate(seg(s, d, "by_segment"), ("study",))
)
_register("merge_bruteforce", seg_sql("orders") + "select cast(sum(c) as bigint) as total_steps, count(*) as unique_steps from (select path, step, count(*) as c from (select path, unnest(range(start, end_)) as step from seg) group by path, step)")(
    lambda s, d: M.merge_bruteforce(seg(s, d, "orders"))
)
_register("merge_unshared", seg_sql("nations") + "select 'none' as sharing, cast(sum(end_ - start) as bigint) as unique_steps from seg union all select 'study', cast(sum(u) as bigint) from (select max(end_) - min(start) as u from seg group by study, path) union all select 'plan', cast(sum(u) as bigint) from (select max(end_) - min(start) as u from seg group by path)")(
    lambda s, d: _sharing(seg(s, d, "nations"))
)


def _sharing(segments: DataFrame) -> DataFrame:
    out = None
    for mode in ("none", "study", "plan"):
        row = M.merge_rate(T.salted(segments, mode)).select(F.lit(mode).alias("sharing"), "unique_steps")
        out = row if out is None else out.unionByName(row)
    return out


def _geo(s: SparkSession, d: str) -> DataFrame:
    c, n, r = (A.table(s, d, x) for x in ("customer", "nation", "region"))
    where = c.join(F.broadcast(n), c["c_nationkey"] == n["n_nationkey"]).join(F.broadcast(r), n["n_regionkey"] == r["r_regionkey"])
    where = where.select(F.col("c_custkey").cast("long").alias("trial"), "r_name", "n_name", "c_mktsegment")
    return seg(s, d, "orders").join(where, "trial")


_GEO = seg_sql("orders") + ", x as (select seg.*, r_name, n_name, c_mktsegment from seg join customer on trial = c_custkey join nation on c_nationkey = n_nationkey join region on n_regionkey = r_regionkey)\n"
_register("merge_rollup_geo", _GEO + "select r_name, n_name, cast(gid as bigint) as grouping_id, cast(sum(t) as bigint) as total, cast(sum(u) as bigint) as \"unique\", round(sum(t) / sum(u), 6) as rate from (select r_name, n_name, grouping(r_name, n_name) as gid, path, sum(end_ - start) as t, max(end_) - min(start) as u from x group by grouping sets ((r_name, n_name, path), (r_name, path), (path))) group by r_name, n_name, gid")(
    lambda s, d: M.merge_rollup(_geo(s, d), ["r_name", "n_name"])
)
_register("merge_cube_hp", _GEO + "select r_name, c_mktsegment, cast(gid as bigint) as grouping_id, cast(sum(t) as bigint) as total, cast(sum(u) as bigint) as \"unique\", round(sum(t) / sum(u), 6) as rate from (select r_name, c_mktsegment, grouping(r_name, c_mktsegment) as gid, path, sum(end_ - start) as t, max(end_) - min(start) as u from x group by grouping sets ((r_name, c_mktsegment, path), (r_name, path), (c_mktsegment, path), (path))) group by r_name, c_mktsegment, gid")(
    lambda s, d: M.merge_rollup(_geo(s, d), ["r_name", "c_mktsegment"], cube=True)
)


def _kwise_sql(kind: str) -> str:
    parts = [
        f"select {len(own)} as k, cast((select sum(end_ - start) from seg where study in ({','.join(repr(x) for x in own)})) as bigint) as total, cast((select sum(u) from (select max(end_) - min(start) as u from seg where study in ({','.join(repr(x) for x in own)}) group by path)) as bigint) as \"unique\", cast((select sum(u) from (select max(end_) - min(start) as u from seg where study in ({','.join(repr(x) for x in own)}) group by study, path)) as bigint) as within_unique"
        for own in HIGH
    ]
    return seg_sql(kind) + "select k, total, \"unique\", within_unique, round(total / \"unique\", 6) as rate from (" + " union all ".join(parts) + ")"


_register("kwise_high", _kwise_sql("high"))(lambda s, d: M.kwise_rate(seg(s, d, "high"), HIGH))
_register("kwise_low", _kwise_sql("low"))(lambda s, d: M.kwise_rate(seg(s, d, "low"), HIGH))
_register("pairwise_rates", seg_sql("nations") + "select a.study as study_a, b.study as study_b, round(sum(t) / sum(u), 6) as rate from (select distinct study from seg) a join (select distinct study from seg) b on a.study < b.study join lateral (select path, sum(end_ - start) as t, max(end_) - min(start) as u from seg where study = a.study or study = b.study group by path) on true group by a.study, b.study")(
    lambda s, d: M.pairwise_rates(seg(s, d, "nations"))
)
_SECONDS = "(values ('F', 0.5::double), ('O', 1.25::double), ('P', 2.0::double)) as sec(cfg, sec)"


def _seconds(s: SparkSession) -> DataFrame:
    return s.createDataFrame([("F", 0.5), ("O", 1.25), ("P", 2.0)], "cfg string, sec double")


_register("cost_rate", seg_sql("nations") + f"select round(sum(t * sec), 6) as cost, round(sum(u * sec), 6) as unique_cost, round(round(sum(t * sec), 6) / round(sum(u * sec), 6), 6) as rate from (select path, min(cfg) as cfg, cast(sum(end_ - start) as double) as t, max(end_) - min(start) as u from seg group by path) n join {_SECONDS} using (cfg)")(
    lambda s, d: M.cost_rate(seg(s, d, "nations"), _seconds(s))
)
_register("coalesce_segments", seg_sql("orders") + "select trial, k, start, end_ as \"end\", cfg from seg")(lambda s, d: seg(s, d, "orders").select("trial", F.col("k").cast("long").alias("k"), "start", "end", "cfg"))
_register("prefix_steps", seg_sql("orders") + "select trial, k, start as before, end_ - start as steps from seg")(lambda s, d: T.prefix_steps(seg(s, d, "orders")).select("trial", F.col("k").cast("long").alias("k"), "before", "steps"))
_register("lineage_paths", seg_sql("orders") + "select trial, k, path, parent, string_agg(start || ':' || cfg, '/') over (partition by study, trial order by k rows unbounded preceding) as text from seg")(
    lambda s, d: T.readable(seg(s, d, "orders")).select("trial", F.col("k").cast("long").alias("k"), "path", "parent", "text")
)
_register("expand_steps", seg_sql("orders") + "select trial, cast(step as bigint) as step, cfg from (select trial, cfg, unnest(range(start, end_)) as step from seg)")(lambda s, d: T.expand_steps(seg(s, d, "orders")).select("trial", "step", "cfg"))
_register("counts", seg_sql("orders") + "select count(*) filter (where k = 0) as trials, count(*) as segments, count(distinct path) as nodes, cast(max(k) as bigint) as max_depth from seg")(
    lambda s, d: M.counts(seg(s, d, "orders")).withColumn("max_depth", F.col("max_depth").cast("long"))
)

# --- forest -------------------------------------------------------------------------------

_STAGES = """, cu as (select path, start as cut from seg union select path, end_ from seg),
st as (select path, cut as lo, lead(cut) over (partition by path order by cut) as hi from cu),
stages as (select s.path, lo, hi, case when s.lo > n.start then s.path else n.parent end as parent_path, case when s.lo > n.start or n.parent is not null then lo end as parent_hi from st s join (select path, min(start) as start, min(parent) as parent from seg group by path) n using (path) where hi is not null)
"""
_TRIALS = ", full_ as (select g.path, g.lo, g.hi, g.parent_path, g.parent_hi, count(*) as trials, min(trial) as min_trial, max(trial) as max_trial from stages g join seg on seg.path = g.path and seg.start <= g.lo and seg.end_ >= g.hi group by all)\n"
_register("stage_cuts", seg_sql("orders") + _STAGES + "select path, lo, hi from stages")(lambda s, d: forest.merge_trials(seg(s, d, "orders")).select("path", "lo", "hi"))
_register("stage_forest", seg_sql("orders") + _STAGES + _TRIALS + "select path, lo, hi, parent_path, parent_hi, trials from full_")(lambda s, d: forest.merge_trials(seg(s, d, "orders")).drop("cfg"))
_register("trials_of_stage", seg_sql("orders") + _STAGES + _TRIALS + "select path, lo, hi, trials as n_trials, min_trial, max_trial from full_")(
    lambda s, d: forest.trials_of_stage(forest.merge_trials(seg(s, d, "orders")), seg(s, d, "orders"))
)
_register("stage_split_insert", seg_sql("orders") + _STAGES + "select path, lo, hi, parent_path, parent_hi from stages")(
    lambda s, d: forest.insert_trials(forest.merge_trials((g := seg(s, d, "orders")).where("trial % 2 = 0")), g.where("trial % 2 = 1"))
)
_register("stage_drop_trials", seg_sql("by_segment").replace("seg as (select", "seg0 as (select") + ", seg as (select * from seg0 where study <> 'BUILDING')" + _STAGES + _TRIALS + "select path, lo, hi, trials from full_")(
    lambda s, d: forest.drop_trials(g := seg(s, d, "by_segment"), g.where("study = 'BUILDING'").select("study", "trial").distinct()).select("path", "lo", "hi", "trials")
)
_register("shared_stage_histogram", seg_sql("orders") + _STAGES + _TRIALS + "select trials as n_trials, count(*) as stages, cast(sum(hi - lo) as bigint) as steps from full_ group by trials")(
    lambda s, d: forest.merge_trials(seg(s, d, "orders")).groupBy(F.col("trials").alias("n_trials")).agg(F.count("*").alias("stages"), F.sum(F.col("hi") - F.col("lo")).alias("steps"))
)

# --- plan ---------------------------------------------------------------------------------

_NODES = ", nodes as (select path, min(parent) as parent, min(start) as start, min(cfg) as cfg, min(k) as depth from seg group by path), req as (select max_by(path, end_) as path, max(end_) as step, trial from seg group by study, trial)\n"
_register("plan_nodes", seg_sql("orders") + _NODES + "select path, parent, start, cfg, depth from nodes")(lambda s, d: plan.plan_nodes(seg(s, d, "orders")).withColumn("depth", F.col("depth").cast("long")))
_register("plan_requests", seg_sql("orders") + _NODES + "select path, step, count(*) as refs from req group by path, step")(lambda s, d: plan.requests(seg(s, d, "orders")))
_register("trials_per_node", seg_sql("orders") + "select path, count(distinct trial) as n from seg group by path")(lambda s, d: seg(s, d, "orders").groupBy("path").agg(F.countDistinct("trial").alias("n")))
_register("approx_trials_per_node")(lambda s, d: seg(s, d, "orders").groupBy("path").agg(F.approx_count_distinct("trial", 0.02).alias("n")))


def _resubmit(s: SparkSession, d: str) -> tuple[DataFrame, plan.Submission]:
    g = seg(s, d, "orders")
    first = plan.empty_plan(g)
    known = first.record(first.submit(g.where("trial % 2 = 0")))
    return g, plan.Plan(known.nodes, known.asked, known.asked).submit(g)


_EVEN = ", ev as (select path from seg where trial % 2 = 0 group by path), evr as (select distinct path, step from req where trial % 2 = 0)\n"
_register("new_nodes_anti", seg_sql("orders") + _NODES + _EVEN + "select path, start from nodes where path not in (select path from ev)")(lambda s, d: _resubmit(s, d)[1].new_nodes.select("path", "start"))
_register("hit_trials_semi", seg_sql("orders") + _NODES + _EVEN + "select r.trial from req r join evr on r.path = evr.path and r.step = evr.step")(
    lambda s, d: (x := _resubmit(s, d)[1]).trial_requests.join(x.answered, ["path", "step"], "left_semi").select("trial")
)
_register("resubmit_hits", seg_sql("orders") + _NODES + _EVEN + "select (select count(*) from evr) as answered, (select count(*) from (select distinct path, step from req) r where not exists (select 1 from evr where evr.path = r.path and evr.step = r.step)) as new_requests")(
    lambda s, d: (x := _resubmit(s, d)[1]).answered.agg(F.count("*").alias("answered")).crossJoin(x.new_requests.agg(F.count("*").alias("new_requests")))
)
_register("plan_diff", seg_sql("orders") + "select coalesce(a.path, b.path) as path, case when a.path is null then 'new' when b.path is null then 'gone' else 'both' end as state from (select distinct path from seg where trial % 2 = 0) a full join (select distinct path from seg where trial % 2 = 1) b on a.path = b.path")(
    lambda s, d: (g := seg(s, d, "orders")).where("trial % 2 = 0").select("path").distinct().alias("a").join(g.where("trial % 2 = 1").select(F.col("path").alias("p")).distinct(), F.expr("path = p"), "full").select(F.coalesce("path", "p").alias("path"), F.when(F.col("path").isNull(), "new").when(F.col("p").isNull(), "gone").otherwise("both").alias("state"))
)
_register("plan_release", seg_sql("orders") + _NODES + "select path, step from req group by path, step having min(trial) % 5 = 0 and max(trial) % 5 = 0 and count(*) filter (where trial % 5 <> 0) = 0")(
    lambda s, d: plan.Plan((g := seg(s, d, "orders")).select("path").distinct(), plan.requests(g).select("path", "step")).release(g, g.where("trial % 5 = 0").select("study", "trial").distinct())
)


def _ckpts(g: DataFrame) -> DataFrame:
    """Synthetic checkpoints: each node's start rounded up to 30, where the node reaches that far."""
    at = (F.ceil(F.col("start") / 30) * 30).cast("long")
    return T.nodes(g).where(at <= F.col("reach")).where(at > F.col("start")).select("path", at.alias("step"))


_CK = ", ck as (select path, cast(ceil(start / 30.0) * 30 as bigint) as step from (select path, min(start) as start, max(end_) as reach from seg group by path) where ceil(start / 30.0) * 30 <= reach and ceil(start / 30.0) * 30 > start)\n"
_NEAR = """, rq as (select distinct path, step from req),
an as (select s.path, s.k, s.start, s.end_, s.trial from seg s),
way as (select r.trial, r.path as node, r.step, a.path as anc, a.k, a.end_ as lim from req r join an a on a.trial = r.trial),
best as (select w.node, w.step, max_by(w.anc, w.k * 1000000 + ck.step) as ckpt_path, max_by(ck.step, w.k * 1000000 + ck.step) as ckpt_step from way w join ck on ck.path = w.anc and ck.step <= w.lim group by w.node, w.step)
"""
_register("nearest_ckpt_asof", seg_sql("orders") + _NODES + _CK + _NEAR + "select rq.path, rq.step, ckpt_path, ckpt_step from rq left join best on rq.path = best.node and rq.step = best.step")(
    lambda s, d: forest.resume_points(plan.requests(g := seg(s, d, "orders")), _ckpts(g), T.lines(g)).drop("up")
)
_register("nearest_ckpt_levels", seg_sql("orders") + _NODES + _CK + _NEAR + "select rq.path, rq.step, ckpt_path, ckpt_step from rq left join best on rq.path = best.node and rq.step = best.step")(
    lambda s, d: forest.climb(plan.requests(g := seg(s, d, "orders")), _ckpts(g), T.nodes(g)).drop("up")
)
_NEED = """, need as (select distinct w.anc as path, case when w.anc = b.ckpt_path then b.ckpt_step else s.start end as lo, w.lim as hi
 from way w left join best b on b.node = w.node and b.step = w.step join (select path, min(start) as start, min(k) as k from seg group by path) s on s.path = w.anc
 left join (select path, min(k) as k from seg group by path) c on c.path = b.ckpt_path where b.ckpt_path is null or s.k >= c.k),
nd as (select * from need where lo < hi)
"""
_BREAK = ", cut as (select path, lo as c from nd union select path, hi from nd), sp as (select path, c as lo, lead(c) over (partition by path order by c) as hi from cut), tree as (select distinct sp.path, sp.lo, sp.hi from sp join nd on nd.path = sp.path and nd.lo <= sp.lo and sp.hi <= nd.hi where sp.hi is not null)\n"


def _tree(s: SparkSession, d: str, mode: str) -> DataFrame:
    g = seg(s, d, "orders")
    return forest.from_plan(plan.requests(g), _ckpts(g), T.lines(g), mode).select("path", "lo", "hi")


_PLAN_SQL = seg_sql("orders") + _NODES + _CK + _NEAR + _NEED + _BREAK
_register("resume_tree_breakpoints", _PLAN_SQL + "select path, lo, hi from tree")(lambda s, d: _tree(s, d, "breakpoints"))
_register("resume_tree_literal", _PLAN_SQL + "select path, lo, hi from nd")(lambda s, d: _tree(s, d, "literal"))
_register("repeated_steps", _PLAN_SQL + "select cast((select sum(hi - lo) from tree) as bigint) as breakpoints, cast((select sum(hi - lo) from nd) as bigint) as literal")(
    lambda s, d: _tree(s, d, "breakpoints").agg(F.sum(F.col("hi") - F.col("lo")).alias("breakpoints")).crossJoin(_tree(s, d, "literal").agg(F.sum(F.col("hi") - F.col("lo")).alias("literal")))
)
_register("ancestors_recursive", seg_sql("orders").replace("with pc", "with recursive pc") + _NODES + ", up as (select path as node, path as ancestor, parent, cast(0 as bigint) as dist from nodes union all select up.node, n.path, n.parent, up.dist + 1 from up join nodes n on n.path = up.parent) select node, ancestor, dist from up")(
    lambda s, d: forest.ancestry(T.lines(seg(s, d, "orders"))).select("node", "ancestor", "dist")
)
for _name, _sql, _op in (("nodes_intersect", "intersect", "intersect"), ("nodes_except", "except", "subtract"), ("nodes_union", "union", "union")):
    _register(_name, seg_sql("high") + f"select path, start from seg where study = '0' {_sql} select path, start from seg where study = '1'")(
        lambda s, d, op=_op: getattr((g := seg(s, d, "high")).where("study = '0'").select("path", "start"), op)(g.where("study = '1'").select("path", "start")).distinct()
    )

# --- schedule -----------------------------------------------------------------------------


def _costed(s: SparkSession, d: str) -> tuple[DataFrame, DataFrame]:
    """(costed stages, lines) of the order histories of all nations."""
    g = seg(s, d, "nations")
    return schedule.costs(forest.merge_trials(g), _seconds(s)), T.lines(g)


_COST = f", costed as (select g.*, (hi - lo) * sec as cost from stages g join (select path, min(cfg) as cfg from seg group by path) c using (path) join {_SECONDS} using (cfg))\n"
_LEAF = """, lf as (select g.path || '@' || hi as leaf, path as node, hi as leaf_hi from costed g where not exists (select 1 from costed c where c.parent_path = g.path and c.parent_hi = g.hi)),
wy as (select distinct a.path as node, b.path as anc, case when b.k < a.k then b.end_ end as lim from seg a join seg b on a.study = b.study and a.trial = b.trial and b.k <= a.k),
lp as (select l.leaf, c.path || '@' || c.hi as stage, c.path, c.lo, c.hi, c.cost from lf l join wy w on w.node = l.node join costed c on c.path = w.anc and c.hi <= coalesce(w.lim, l.leaf_hi)),
tt as (select *, sum(cost) over (partition by leaf) as total from lp),
el as (select stage, any_value(path) as path, any_value(lo) as lo, any_value(hi) as hi, any_value(cost) as cost, first(leaf order by total desc, leaf) as leaf from tt group by stage),
ch as (select leaf, sum(cost) as cost, count(*) as n_stages, min(lo) as lo from el group by leaf)
"""
_SCHED = seg_sql("nations") + _STAGES + _COST + _LEAF
_register("stage_costs", seg_sql("nations") + _STAGES + _COST + "select path, lo, hi, cost from costed")(lambda s, d: _costed(s, d)[0].select("path", "lo", "hi", "cost"))
_register("critical_path", _SCHED + "select leaf, max(total) as total from tt group by leaf order by total desc, leaf limit 1")(lambda s, d: schedule.critical_path(*_costed(s, d)))
_register("chains_orders", _SCHED + "select leaf, cost, n_stages, lo from ch")(lambda s, d: schedule.chains(*_costed(s, d)))
_register("chains_levels", _SCHED + "select leaf, cost, n_stages, lo from ch")(lambda s, d: schedule.chains(_costed(s, d)[0]))
_register("top_chains", _SCHED + "select leaf, cost, n_stages, lo from ch order by cost desc, leaf limit 40")(lambda s, d: schedule.top_chains(*_costed(s, d), 40))
_register("bfs_order", seg_sql("nations") + _STAGES + "select path, lo, hi, depth from stages join (select path, min(k) as depth from seg group by path) using (path)")(
    lambda s, d: schedule.breadth_first(forest.merge_trials(g := seg(s, d, "nations")), T.nodes(g))
)


def _elected(s: SparkSession, d: str) -> DataFrame:
    """Stages with their chains, each nation a study with a plan and a cluster of its own."""
    g = T.salted(seg(s, d, "nations"), "study")
    st = schedule.costs(forest.merge_trials(g), _seconds(s))
    up = st.select(schedule.stage_id(F.col("path"), F.col("hi")).alias("stage"), schedule.stage_id(F.col("parent_path"), F.col("parent_hi")).alias("parent"))
    return schedule.elected_leaves(st, T.lines(g)).join(up, "stage").withColumn("study", F.expr("substring(substring_index(path, '~', 1), 2)"))


SWEEP = [(p, w) for w in (1, 4, 8, 40) for p in ("chains", "breadth")]
_register("makespan_sweep")(lambda s, d: simulate.run(_elected(s, d), SWEEP))
_register("sched_bfs_vs_cp")(lambda s, d: simulate.run(_elected(s, d), [(p, w) for p, w in SWEEP if w == 8], save=1.0, load=1.0))
_register("transition_costs")(lambda s, d: reduce(DataFrame.unionByName, [
    simulate.run(_elected(s, d), [(p, w) for p, w in SWEEP if w in (8, 40)], save=c, load=c).withColumn("cost", F.lit(c)) for c in (0.0, 1.0, 5.0, 20.0)
]))
_register("work_bound", _SCHED + "select 40 as w, sum(cost) as work, (select max(total) from tt) as path, greatest(sum(cost) / 40, (select max(total) from tt)) as least from el")(
    lambda s, d: simulate.bounds(*_costed(s, d), 40)
)

# --- settings and spaces ------------------------------------------------------------------

_FUNCTIONS = {
    "exponential": ([0.1, 0.95], "0.1 * pow(0.95, step)"),
    "linear": ([0.1, 0.0, 100.0], "0.1 + (0.0 - 0.1) * step / 100.0"),
}
for _fn, (_args, _sql) in _FUNCTIONS.items():
    _register(f"hp_values_{_fn}", f"select step, round(cast({_sql} as double), 9) as value from (select unnest(range(0, 100)) as step)")(
        lambda s, d, fn=_fn, args=_args: s.range(100).select(F.col("id").alias("step"), F.round(H.value(F.lit(fn), F.array(*[F.lit(x) for x in args]), F.col("id")), 9).alias("value"))
    )
_FAMILIES = {
    "step": (lambda: H.step_decay(0.1, 0.1, [30, 60], 100), "case when step < 30 then 0.1 when step < 60 then 0.01 else 0.001 end"),
    "warmup": (lambda: H.warmup(10, 0.1, H.exponential(0.1, 0.9, 90)), "case when step < 10 then 0.1 * step / 10.0 else 0.1 * pow(0.9, step - 10) end"),
    "restarts": (lambda: H.cosine_restarts(0.1, 20, 100), "0.1 * (1 + cos(pi() * (step % 20) / 20.0)) / 2"),
    "multi": (lambda: H.multi_value([128, 256, 512], [40, 80], 100), "case when step < 40 then 128 when step < 80 then 256 else 512 end"),
}


def _spans(s: SparkSession, pieces: list[H.Piece]) -> DataFrame:
    rows, at = [], 0
    for p in pieces:
        rows.append((at, at + p.length, p.fn, list(p.args), p.since))
        at += p.length
    return s.createDataFrame(rows, "lo long, hi long, fn string, args array<double>, since long")


def _family(s: SparkSession, pieces: list[H.Piece]) -> DataFrame:
    t = _spans(s, pieces)
    t = t.select("*", F.explode(F.sequence("lo", F.col("hi") - 1)).alias("step"))
    return t.select("step", F.round(H.value(F.col("fn"), F.col("args"), F.col("step") - F.col("lo") + F.col("since")), 9).alias("value"))


for _fn, (_make, _sql) in _FAMILIES.items():
    _register(f"hp_values_{_fn}", f"select step, round(cast({_sql} as double), 9) as value from (select unnest(range(0, 100)) as step)")(lambda s, d, make=_make: _family(s, make()))
_REPORTED = "(select event_id, cast(json_extract(props, '$.k') as bigint) as step from events)"


def _reported(s: SparkSession, d: str) -> DataFrame:
    """(event_id, step): the step of each report of the event stream."""
    return A.table(s, d, "events").select("event_id", F.from_json("props", "k bigint")["k"].alias("step"))


def _at_reports(s: SparkSession, d: str, fn: str, args: list[float]) -> DataFrame:
    return _reported(s, d).select("event_id", "step", F.round(H.value(F.lit(fn), F.array(*[F.lit(x) for x in args]), F.col("step")), 9).alias("value"))


def _spans_at_reports(s: SparkSession, d: str, pieces: list[H.Piece]) -> DataFrame:
    """The same of a setting of several pieces; null where a report lies beyond its end."""
    own = _reported(s, d).join(F.broadcast(_spans(s, pieces)), F.expr("step >= lo and step < hi"), "left")
    return own.select("event_id", "step", F.round(H.value(F.col("fn"), F.col("args"), F.col("step") - F.col("lo") + F.col("since")), 9).alias("value"))


_register("hp_values_constant", f"select event_id, step, round(cast(0.1 as double), 9) as value from {_REPORTED}")(lambda s, d: _at_reports(s, d, "constant", [0.1]))
_register("hp_values_cosine", f"select event_id, step, round(cast(0.001 + (0.1 - 0.001) * (1 + cos(pi() * step / 100.0)) / 2 as double), 9) as value from {_REPORTED}")(
    lambda s, d: _at_reports(s, d, "cosine", [0.1, 100.0, 0.001])
)
_register("hp_values_cyclic", f"select event_id, step, round(cast(case when step < 0 or step >= 100 then null when (step // 10) % 2 = 0 then 0.001 + 0.099 * (step % 10) / 10.0 else 0.1 - 0.099 * (step % 10) / 10.0 end as double), 9) as value from {_REPORTED}")(
    lambda s, d: _spans_at_reports(s, d, H.cyclic(0.001, 0.1, 10, 100))
)


def steps_sql(studies: list[tuple[str, dict]]) -> str:
    """with-clause up to ``hist``(study, trial, step, h): what each trial of some grids has trained up to each step, by the settings' values at each single step.

    It knows nothing of segments or nodes: settings are spread over steps, and a history is the digest of all symbols so far.
    """
    rows = []
    for study, families in studies:
        for hp, options in families.items():
            for i, pieces in enumerate(options):
                at = 0
                for x in pieces:
                    rows.append(f"('{study}','{hp}',{i},{at},{at + x.length},'{x.text()}',{at - x.since})")
                    at += x.length
    hps = list(studies[0][1])
    cross = " join ".join(f"(select distinct study, i as i{k} from pc where hp = '{hp}') o{k}" + ("" if not k else f" on o{k}.study = o0.study") for k, hp in enumerate(hps))
    joined = " ".join(f"join hs h{k} on h{k}.study = t.study and h{k}.hp = '{hp}' and h{k}.i = t.i{k}" + ("" if not k else " and h%d.step = h0.step" % k) for k, hp in enumerate(hps))
    return f"""with pc(study, hp, i, lo, hi, piece, zero) as (values {",".join(rows)}),
sy as (select study, hp, i, cast(step as bigint) as step, case when piece like 'constant%' then piece else piece || '@' || (step - zero) end as symbol from (select *, unnest(range(lo, hi)) as step from pc)),
hs as (select study, hp, i, step, md5(string_agg(symbol, '|') over (partition by study, hp, i order by step rows unbounded preceding)) as h from sy),
tr as (select o0.study, {", ".join(f"i{k}" for k in range(len(hps)))} from {cross}),
hist as (select t.study, t.study || {" || '-' || ".join(f"i{k}" for k in range(len(hps)))} as trial, h0.step, {" || ".join(f"h{k}.h" for k in range(len(hps)))} as h from tr t {joined})
"""


_SPACES = {"w4": [("w4", space.families_w4())], "w6": [("w6", space.families_w6())], "w7": [("w7", space.families_w7())]}
_SPACES |= {f"w8_s{k}": [(str(i), space.families_w8(i)) for i in range(k)] for k in (1, 2, 4, 8)}
_SPACES |= {f"w9_s{k}": [(str(i), space.families_w9(i)) for i in range(k)] for k in (1, 2, 4, 8)}
_SPACES["small"] = [("small", space.families_small())]
_COUNTED = "select count(distinct trial) as trials, count(*) as total_steps, count(distinct step || h) as unique_steps, round(count(*) / count(distinct step || h), 6) as rate from hist"


def _space(s: SparkSession, name: str) -> DataFrame:
    return reduce(DataFrame.unionByName, [space.grid(s, study, families) for study, families in _SPACES[name]])


for _name in _SPACES:
    _register(f"space_{_name}", steps_sql(_SPACES[_name]) + _COUNTED)(lambda s, d, n=_name: M.merge_rate(T.canonical(_space(s, n))).drop("nodes"))
_register("grid_cross", "select distinct p_brand, p_size from (select distinct p_brand from part) cross join (select distinct p_size from part)")(
    lambda s, d: (p := A.table(s, d, "part")).select("p_brand").distinct().crossJoin(F.broadcast(p.select("p_size").distinct()))
)
_register("filter_conditional_space", "select p_brand, p_size from (select distinct p_brand from part) cross join (select distinct p_size from part) where not (p_brand like '%1' and p_size > 25)")(
    lambda s, d: _Q["grid_cross"](s, d).where("not (p_brand like '%1' and p_size > 25)")
)
_register("random_search", "select trial from (select distinct o_custkey as trial from orders) order by md5('7-' || trial) limit 50")(
    lambda s, d: space.sample(A.table(s, d, "orders").select(F.col("o_custkey").alias("trial")).distinct(), 50, 7)
)

# --- tuners -------------------------------------------------------------------------------

_METRICS = "with m as (select 'events' as study, user_id as trial, row_number() over (partition by user_id order by ts, event_id) as step, value from events)\n"


def _metrics(s: SparkSession, d: str) -> DataFrame:
    e = A.table(s, d, "events")
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    return e.select(F.lit("events").alias("study"), F.col("user_id").cast("long").alias("trial"), F.row_number().over(w).cast("long").alias("step"), "value", "ts", "event_id")


def _rungs_sql(steps: list[int], keeps: list[str]) -> str:
    parts, out = [_METRICS.rstrip()], []
    alive = "select distinct trial from m"
    for k, (step, keep) in enumerate(zip(steps, keeps)):
        parts.append(f"r{k} as (select study, trial, cast({step} as bigint) as rung, row_number() over (order by value desc, trial) as rank, count(*) over () as n from m where step = {step} and trial in ({alive}))")
        out.append(f"select study, trial, rung, rank, {keep} as action from r{k}")
        alive = f"select trial from (select trial, {keep} as action from r{k}) where action = 'promote'"
    return ", ".join(parts) + "\n" + " union all ".join(out)


_half = "case when rank <= greatest(n // 4, 1) then 'promote' else 'stop' end"
_register("sha_rungs", _rungs_sql([2, 8, 32, 40], [_half, _half, _half, "'finish'"]))(lambda s, d: tuners.halving(_metrics(s, d), 4, 2, 40))
_register("milestone_stop", _rungs_sql([5, 10], ["case when rank <= 8 then 'promote' else 'stop' end", "case when rank <= 4 then 'promote' else 'stop' end"]))(lambda s, d: tuners.milestones(_metrics(s, d), [(5, 8), (10, 4)]))
_register("hyperband_brackets", "select cast(s as int) as bracket, cast(ceil(2.0 / (s + 1) * pow(4, s)) as int) as trials, cast(round(120 * pow(4, -s)) as int) as first_step from (select unnest(range(0, 2)) as s)")(
    lambda s, d: s.createDataFrame([tuple(int(v) for v in x.values()) for x in tuners.hyperband(4, 15, 120)], "bracket int, trials int, first_step int")
)
_register("median_stop", _METRICS.rstrip() + """, r as (select study, trial, step, avg(value) over w as mean, max(value) over w as best from m window w as (partition by trial order by step rows unbounded preceding)),
x as (select a.study, a.trial, a.step from r a join r b on a.step = b.step and a.trial <> b.trial where a.step >= 5 group by a.study, a.trial, a.step, a.best having count(*) >= 3 and a.best < median(b.mean))
select study, trial, min(step) as stop_at from x group by study, trial""")(lambda s, d: tuners.median_stop(_metrics(s, d), 5))
_register("pbt_quartiles", _METRICS.rstrip() + """, q as (select trial, row_number() over (order by value desc, trial) as r, count(*) over () as n from m where step = 20),
t as (select trial as donor, r - 1 as slot from q where r <= greatest(n // 5, 1)),
l as (select trial, cast('0x' || substr(md5('1-20-' || trial), 1, 8) as bigint) % greatest(n // 5, 1) as slot from q where r > n - greatest(n // 5, 1))
select 'events' as study, l.trial, t.donor from l join t using (slot)""")(lambda s, d: tuners.population(_metrics(s, d), 20))


def _ordered(s: SparkSession, d: str) -> DataFrame:
    """Reports of two studies, which share out the users, with an order of arrival."""
    return _metrics(s, d).withColumn("study", F.concat(F.lit("s"), (F.col("trial") % 2).cast("string"))).withColumn("ord", F.date_format("ts", "yyyyMMddHHmmss.SSSSSS")).withColumn("ord", F.concat("ord", F.format_string("-%020d", F.col("event_id"))))


_register("asha_replay")(lambda s, d: tuners.async_replay(_ordered(s, d), 4, [2, 8, 32]))
_register("best_trial", _METRICS + "select trial, step, value from m order by value desc, trial, step limit 1")(lambda s, d: M.best(_metrics(s, d)))
_register("topk_per_study", "select event_type, user_id, value from (select *, row_number() over (partition by event_type order by value desc, event_id) as r from events) where r <= 3")(
    lambda s, d: A.table(s, d, "events").withColumn("r", F.row_number().over(Window.partitionBy("event_type").orderBy(F.desc("value"), "event_id"))).where("r <= 3").select("event_type", "user_id", "value")
)
_register("metric_pivot", _METRICS + "select trial, max(value) filter (where step = 1) as \"1\", max(value) filter (where step = 2) as \"2\", max(value) filter (where step = 3) as \"3\" from m where step <= 3 group by trial")(
    lambda s, d: _metrics(s, d).groupBy("trial").pivot("step", [1, 2, 3]).agg(F.max("value"))
)
# every step of every trial, as the pivot has a column for the first three only
_register("metric_steps", _METRICS + "select trial, map_from_entries(list((step, value) order by step)) as \"values\" from m group by trial")(
    lambda s, d: _metrics(s, d).groupBy("trial").agg(F.map_from_entries(F.array_sort(F.collect_list(F.struct("step", "value")))).alias("values"))
)
_register("smoothed_metric", _METRICS + "select trial, step, round(avg(value) over (partition by trial order by step rows 4 preceding), 6) as smooth from m")(
    lambda s, d: _metrics(s, d).select("trial", "step", F.round(F.avg("value").over(Window.partitionBy("trial").orderBy("step").rowsBetween(-4, 0)), 6).alias("smooth"))
)
_register("curve_slope", _METRICS + "select trial, round(regr_slope(value, step), 6) as slope from m group by trial")(lambda s, d: _metrics(s, d).groupBy("trial").agg(F.round(F.regr_slope("value", "step"), 6).alias("slope")))
_register("config_changes", seg_sql("orders") + "select trial, k, lag(cfg) over (partition by trial order by k) as before, cfg as after from seg qualify before is not null")(
    lambda s, d: seg(s, d, "orders").select("trial", F.col("k").cast("long").alias("k"), F.lag("cfg").over(Window.partitionBy("study", "trial").orderBy("k")).alias("before"), F.col("cfg").alias("after")).where("before is not null")
)
_register("props_step", "select event_id, cast(json_extract(props, '$.k') as bigint) as step from events")(lambda s, d: A.table(s, d, "events").select("event_id", F.from_json("props", "k bigint")["k"].alias("step")))
_register("reports_by_day", "select cast(cast(ts as date) as varchar) as day, event_type, count(*) as n from events group by all")(lambda s, d: A.table(s, d, "events").groupBy(F.date_format("ts", "yyyy-MM-dd").alias("day"), "event_type").agg(F.count("*").alias("n")))
# batches of one epoch over all reports: two of 3 rows, then of 2; the factor is the first one without a common factor with the number of rows
_register("batch_slices", """with r as (select event_id, row_number() over (order by event_id nulls first) - 1 as row_no from events), n as (select nullif(count(*), 0) as n from r),
ab as (select n, 31 % n as b, min_by((7919 + 1 + k) % n, k) as a from n, (select unnest(range(0, 1000)) as k) where gcd((7919 + 1 + k) % n, n) = 1 group by n),
slot as (select row_no as i, case when row_no < 6 then row_no // 3 else 2 + (row_no - 6) // 2 end as batch from r)
select batch, row_no, event_id from (select batch, (a * i + b) % n as row_no from slot, ab) join r using (row_no)""")(lambda s, d: training.batch_slices(A.table(s, d, "events"), "event_id", [3, 3, 2], 1))

# --- figures ------------------------------------------------------------------------------

_FOUR = [(1, 0, "0.1", 200), (1, 1, "0.01", 100), (2, 0, "0.1", 100), (2, 1, "0.05", 100), (2, 2, "0.01", 100), (3, 0, "0.1", 100), (3, 1, "0.05", 100), (3, 2, "0.02", 100), (4, 0, "0.1", 100), (4, 1, "0.05", 200)]


def literal(s: SparkSession, rows: list[tuple]) -> DataFrame:
    return T.canonical(s.createDataFrame([("fig", *r) for r in rows], "study string, trial bigint, ord bigint, cfg string, steps bigint"))


_STUDY_RATE = "select study, cast(sum(r) as bigint) as trials, cast(sum(t) as bigint) as total_steps, cast(sum(u) as bigint) as unique_steps, round(sum(t) / sum(u), 6) as rate from (select study, path, sum(end_ - start) as t, max(end_) - min(start) as u, count(*) filter (where k = 0) as r from seg group by study, path) group by study"
_OWN_TREES = ", seg as (select * replace ('s' || study || '~' || path as path, 's' || study || '~' || parent as parent) from seg0)\n"
# the orders of four neighbouring customers are the four trials of a study, and a fifth one's come to them
_register("fig_four_trials", seg_sql("block4").replace("seg as (select", "seg0 as (select") + _OWN_TREES + _STAGES + _TRIALS + "select substr(split_part(path, '~', 1), 2) as study, split_part(path, '~', 2) as path, lo, hi, trials from full_")(
    lambda s, d: forest.merge_trials(T.salted(seg(s, d, "block4"), "study")).select(F.expr("substring(substring_index(path, '~', 1), 2)").alias("study"), F.substring_index("path", "~", -1).alias("path"), "lo", "hi", "trials")
)
_register("fig_fifth_trial", seg_sql("block5") + _STUDY_RATE)(lambda s, d: M.merge_rate(seg(s, d, "block5"), ("study",)).drop("nodes"))
# a customer's orders of one status begin alike and part by their priority
_register("fig_two_pairs", seg_sql("pairs") + _STUDY_RATE)(lambda s, d: M.merge_rate(seg(s, d, "pairs"), ("study",)).drop("nodes"))


def fig_plan(s: SparkSession) -> tuple[DataFrame, DataFrame, DataFrame]:
    """(requests, checkpoints, lines) of the plan of four nodes."""
    g = literal(s, [(1, 0, "H1", 15), (2, 0, "H1", 10), (2, 1, "H2", 15), (3, 0, "H1", 20), (3, 1, "H3", 15), (4, 0, "H1", 20), (4, 1, "H3", 20), (4, 2, "H4", 20)])
    saved = [(T.identity(*_N1), 10), (T.identity(*_N1), 20), (T.identity(*_N2), 20)]
    return plan.requests(g).select("path", "step"), s.createDataFrame(saved, "path string, step bigint"), T.lines(g)


_N1, _N2, _N3, _N4 = [(0, "H1")], [(0, "H1"), (10, "H2")], [(0, "H1"), (20, "H3")], [(0, "H1"), (20, "H3"), (40, "H4")]


def _year_plan(s: SparkSession, d: str) -> tuple[Scratch, DataFrame, tuple[DataFrame, DataFrame, DataFrame]]:
    """(scratch, nodes, (requests, checkpoints, lines)) of the plan of all years of orders, trained so far up to step 20 with a checkpoint each 10 steps."""
    scratch = Scratch(s, "years")
    g = scratch.save(seg(s, d, "years"), "segments")
    asked, lines, nodes = scratch.save(plan.requests(g).select("path", "step"), "asked"), scratch.save(T.lines(g), "lines"), scratch.save(T.nodes(g), "nodes")
    saved = nodes.select("path", "start", "reach", F.explode(F.array(F.lit(10).cast("long"), F.lit(20).cast("long"))).alias("step")).where("step > start and step <= reach").select("path", "step")
    return scratch, nodes, (asked, saved, lines)


_SAVED = ", ck as (select path, cast(s as bigint) as step from (select path, min(start) as start, max(end_) as reach from seg group by path) join (values (10), (20)) as t(s) on s > start and s <= reach)\n"
_YEARS = seg_sql("years") + _NODES + _SAVED + _NEAR + _NEED + _BREAK
_register("fig_plan_tree", _YEARS + "select path, lo, hi from tree")(lambda s, d: forest.from_plan(*_year_plan(s, d)[2]).select("path", "lo", "hi"))
_register("fig_plan_literal", _YEARS + "select path, lo, hi from nd")(lambda s, d: forest.from_plan(*_year_plan(s, d)[2], "literal").select("path", "lo", "hi"))
_HELD = """, hd as (select t.path, t.lo from tree t join nodes n on n.path = t.path and n.start = 20 and t.lo = 20 and n.cfg = 'H3'),
wy as (select distinct a.path, b.path as up from seg a join seg b on a.study = b.study and a.trial = b.trial and b.k <= a.k)
"""


def _years_running(s: SparkSession, d: str) -> DataFrame:
    """The same plan while workers train the H3 nodes that start at step 20, up to their first cut: what follows is blocked."""
    scratch, nodes, own = _year_plan(s, d)
    third = nodes.where("start = 20 and cfg = 'H3'").select("path")
    held = scratch.save(forest.from_plan(*own).where("lo = 20").join(third, "path", "left_semi").select("path", "lo", "hi"), "held")
    return forest.from_plan(*own, running=held).select("path", "lo", "hi", "blocked")


_register("fig_plan_running", _YEARS.rstrip() + _HELD + "select path, lo, hi, path in (select wy.path from wy join hd on hd.path = wy.up) as blocked from tree where not exists (select 1 from hd where hd.path = tree.path and hd.lo = tree.lo)")(lambda s, d: _years_running(s, d))

# --- training -----------------------------------------------------------------------------


def _vectors(s: SparkSession, d: str) -> tuple[DataFrame, DataFrame]:
    """(rows to learn from, held-out rows): the class is the position of the largest of the first ten coordinates."""
    ten = F.slice("embedding", 1, 10)
    v = A.table(s, d, "embeddings").select(F.col("vec_id").alias("id"), F.col("embedding").alias("x"), (F.array_position(ten, F.array_max(ten)) - 1).alias("y"))
    out = F.crc32(F.col("id").cast("string")) % 5 == 0
    return v.where(~out), v.where(out)


def _study(s: SparkSession, d: str, pieces: DataFrame, model: type = training.Softmax, source=_vectors, classes: int = 10, measure: str = "value") -> DataFrame:
    """All trials of a space, alone and with sharing: (mode, trials, steps_run, best, equal); equal: both modes give the same bits."""
    learn, held = source(s, d)
    data, own = training.fit_sample(learn), T.canonical(pieces).withColumn("ckpt", F.lit(None).cast("binary"))
    scratch = Scratch(s, "study")
    alone, shared = (scratch.save(training.train(own, data, classes, x, model=model), f"shared-{x}") for x in (False, True))
    best = training.scores(shared, held, model).agg(F.max(measure).alias("best"))
    differ = alone.select("study", "trial", "ckpt").exceptAll(shared.select("study", "trial", "ckpt")).agg((F.count("*") == 0).alias("equal"))
    told = [t.agg(F.lit(m).alias("mode"), F.count("*").alias("trials"), F.sum("steps_run").alias("steps_run")) for m, t in (("trial", alone), ("stage", shared))]
    return told[0].unionByName(told[1]).join(F.broadcast(best)).join(F.broadcast(differ))


def _texts(s: SparkSession, d: str) -> tuple[DataFrame, DataFrame]:
    """(rows to learn from, held-out rows) of the labelled documents: hashed words, quality as class.

    A row to learn from has the words up to the longest value of the setting ``length``, which is what is tuned; held-out texts are whole.
    """
    most = max(int(x.args[0]) for option in space.families_w7()["length"] for x in option)
    words = F.filter(F.split(F.lower(F.coalesce("text", F.lit(""))), "[ \\t\\n\\r]+"), lambda w: w != "")
    buckets = F.transform(words, lambda w: F.pmod(F.xxhash64(w), F.lit(training.WordBag.BUCKETS)).cast("double"))
    t = A.table(s, d, "documents").select("doc_id", "text").join(A.table(s, d, "labels").select("doc_id", "quality").where("quality is not null"), "doc_id")
    t = t.select(F.col("doc_id").alias("id"), buckets.alias("x"), F.col("quality").cast("long").alias("y"))
    out = F.crc32(F.col("id").cast("string")) % 5 == 0
    padded = F.concat(F.slice("x", 1, most), F.array_repeat(F.lit(-1.0), F.greatest(F.lit(most) - F.size("x"), F.lit(0))))
    return t.where(~out).withColumn("x", padded), t.where(out)


def _study_halving(s: SparkSession, d: str, pieces: DataFrame, eta: int, rungs: list[int]) -> DataFrame:
    """Successive halving that trains: (mode, rung, trials, steps_run, best); the trials that stay resume from their states."""
    learn, held = _vectors(s, d)
    data, out, scratch = training.fit_sample(learn), None, Scratch(s, "halving")
    for mode in ("trial", "stage"):
        own, lo = T.canonical(pieces).withColumn("ckpt", F.lit(None).cast("binary")), 0
        for hi in rungs:
            done = scratch.save(training.train(own, data, 10, mode == "stage", lo, hi), f"{mode}-{hi}")
            value = scratch.save(training.scores(done, held), f"{mode}-{hi}-values")
            row = done.agg(F.lit(mode).alias("mode"), F.lit(hi).cast("long").alias("rung"), F.count("*").alias("trials"), F.sum("steps_run").alias("steps_run")).join(F.broadcast(value.agg(F.round(F.max("value"), 6).alias("best"))))
            out = row if out is None else out.unionByName(row)
            stay = value.orderBy(F.desc("value"), "study", "trial").limit(max(1, done.count() // eta)).select("study", "trial")
            own, lo = own.drop("ckpt").join(F.broadcast(stay), ["study", "trial"]).join(done.select("study", "trial", "ckpt"), ["study", "trial"]), hi
    return out


_TWO = [(1, 0, "bs=constant(32);lr=constant(0.5)", 200), (2, 0, "bs=constant(32);lr=constant(0.5)", 100), (2, 1, "bs=constant(32);lr=constant(0.05)", 50), (2, 2, "bs=constant(32);lr=constant(0.005)", 50)]
_register("curve_two_trials")(lambda s, d: _study(s, d, s.createDataFrame([("w3", *r) for r in _TWO], "study string, trial bigint, ord bigint, cfg string, steps bigint")))
_register("study_grid_cutout")(lambda s, d: _study(s, d, space.w6(s), training.OneHidden))
_register("study_grid_seqlen")(lambda s, d: _study(s, d, space.w7(s), training.WordBag, _texts, 2, "f1"))
_register("study_sha")(lambda s, d: _study_halving(s, d, space.w4(s), 4, [15, 60, 120]))
for _k in (1, 2, 4, 8):
    _register(f"multi_high_s{_k}")(lambda s, d, k=_k: _study(s, d, space.w8(s, k)))
    _register(f"multi_low_s{_k}")(lambda s, d, k=_k: _study(s, d, space.w9(s, k)))
# what training runs is what the settings' values at each step say
_register("study_steps", steps_sql(_SPACES["w6"]) + "select 'stage' as mode, count(distinct trial) as trials, count(distinct step || h) as steps_run from hist union all select 'trial', count(distinct trial), count(*) from hist")(
    lambda s, d: _study(s, d, space.w6(s)).select("mode", "trials", "steps_run")
)
_register("lossless_check", steps_sql(_SPACES["w6"]) + "select count(distinct trial) as trials, cast(0 as bigint) as differing from hist")(lambda s, d: _lossless(s, d))


def _lossless(s: SparkSession, d: str) -> DataFrame:
    """Trials, and how many of them end in another state when their steps are shared: compared byte by byte."""
    learn, _ = _vectors(s, d)
    data, own = training.fit_sample(learn), T.canonical(space.w6(s)).withColumn("ckpt", F.lit(None).cast("binary"))
    alone, shared = (training.train(own, data, 10, x).select("study", "trial", F.col("ckpt").alias(f"c{int(x)}")) for x in (False, True))
    return alone.join(shared, ["study", "trial"], "full").agg(F.count("*").alias("trials"), F.count_if(~F.col("c0").eqNullSafe(F.col("c1"))).alias("differing"))


# --- studies on a plan --------------------------------------------------------------------


def _client(s: SparkSession, d: str, workers: int = 40) -> tuple[Study, DataFrame]:
    """A new study of 16 trials, with a plan of its own, and its trials."""
    learn, held = _vectors(s, d)
    own = Study.open(s, "small", training.Softmax, "embeddings", ["lr", "bs"], training.fit_sample(learn), held, 10, root=Scratch(s, "plans").root, workers=workers, every=8)
    return own, own.engine.scratch.save(own.trials(space.families_small()), "trials")


def _loop(s: SparkSession, d: str) -> tuple[Study, DataFrame, list]:
    own, g = _client(s, d, workers=4)
    own.engine.submit(g)
    return own, g, own.engine.run()


_register("loop_rounds")(lambda s, d: s.createDataFrame([(r.number, r.chains, r.stages, r.steps, r.open) for r in _loop(s, d)[2]], "round bigint, chains bigint, stages bigint, steps bigint, open bigint"))


def _loop_totals(s: SparkSession, d: str) -> DataFrame:
    """What the loop trained, whether every trial ends in the state of training it alone, and what a second submission costs."""
    own, g, rounds = _loop(s, d)
    alone = training.train(g.withColumn("ckpt", F.lit(None).cast("binary")), own.engine.data, 10, False).select("study", "trial", F.col("ckpt").alias("alone"))
    differ = own.engine.checkpoints(g).join(alone, ["study", "trial"], "full").where(~F.col("ckpt").eqNullSafe(F.col("alone"))).count()
    hits, fresh = own.engine.submit(g)
    again = sum(r.steps for r in own.engine.run())
    row = (own.engine.results(g).count(), sum(r.steps for r in rounds), differ, hits, fresh, again)
    return s.createDataFrame([row], "trials bigint, steps_run bigint, differing bigint, answered_again bigint, new_again bigint, steps_again bigint")


_register("loop_totals", steps_sql(_SPACES["small"]) + "select count(distinct trial) as trials, count(distinct step || h) as steps_run, cast(0 as bigint) as differing, (select count(distinct h) from hist where step = 63) as answered_again, cast(0 as bigint) as new_again, cast(0 as bigint) as steps_again from hist")(_loop_totals)


def _counted(told: DataFrame) -> DataFrame:
    return told.groupBy("rung").agg(F.count("*").alias("trials"), F.count_if(F.col("action") == "promote").alias("promoted"))


_N = ", n as (select count(distinct trial) as n from hist)\n"
_register("tune_grid", steps_sql(_SPACES["small"]) + _N + "select cast(64 as bigint) as rung, n as trials, cast(0 as bigint) as promoted from n")(lambda s, d: _counted(_tuned(s, d, study.grid(64))))
_register("tune_halving", steps_sql(_SPACES["small"]) + _N + "select cast(4 as bigint) as rung, n as trials, n // 4 as promoted from n union all select 16, n // 4, n // 16 from n union all select 64, n // 16, 0 from n")(lambda s, d: _counted(_tuned(s, d, study.halving(4, 4, 64))))
_register("tune_milestones", steps_sql(_SPACES["small"]) + _N + "select cast(8 as bigint) as rung, n as trials, 6 as promoted from n union all select 24, 6, 2 union all select 64, 2, 0")(lambda s, d: _counted(_tuned(s, d, study.milestones([(8, 6), (24, 2), (64, 1)]))))
_register("tune_hyperband")(lambda s, d: _tuned(s, d, study.hyperband(2, 16, 64)).select("bracket", "rung", "rank", "trial", "action", "value"))
_register("tune_async")(lambda s, d: _tuned(s, d, study.async_halving(4, 4, 64)).select("trial", "rung", "rank", "value"))
_register("tune_median")(lambda s, d: _tuned(s, d, study.median_stop(16, 64, 16)).select("trial", "rung", "rank", "action", "value"))
_register("tune_population")(lambda s, d: _tuned(s, d, study.population(16, 64)).select("trial", "rung", "rank", "action", "donor", "value"))


def _tuned(s: SparkSession, d: str, tuner) -> DataFrame:
    own, g = _client(s, d)
    return own.tune(tuner, g)


def _client_calls(s: SparkSession, d: str) -> DataFrame:
    """Two tuners on one study, its winner trained further, and one configuration evaluated: (call, steps) that each of them had to train."""
    own, g = _client(s, d)
    calls = []
    trained = lambda: sum(r.steps for r in own.engine.rounds)

    def call(name: str, f):
        before, out = trained(), f()
        calls.append((name, trained() - before))
        return out

    best = call("halving", lambda: own.tune(study.halving(4, 4, 64), g))
    call("halving again", lambda: own.tune(study.halving(4, 4, 64), g))
    call("winner", lambda: own.finish(g, best, 16))
    call("grid", lambda: own.tune(study.grid(64), g))
    call("evaluate", lambda: own.evaluate({k: v[0] for k, v in space.families_small().items()}, 64))
    return s.createDataFrame(calls, "call string, steps bigint")


_register("study_calls")(_client_calls)

# --- experiments on forty workers ---------------------------------------------------------

WORKERS, EXTRA = 40, 100.0


def _single(s: SparkSession, d: str) -> DataFrame:
    """The four studies of one space each: (workload, way, worker_time, makespan, their ratios to the external tuner's, transitions, rate, explored, best, target).

    The winner of the image studies trains 100 epochs more, which both times hold.  A trial of the text study takes four
    workers at once.  ``target`` is what the first trial of the space reaches when it is trained alone.
    """
    g4, g6, g7 = (T.canonical(getattr(space, w)(s)) for w in ("w4", "w6", "w7"))
    best = lambda m: m.agg(F.max("value")).first()[0]
    first = lambda g, *x, **y: best(X.curves(g.where("trial = 0"), *x, **y, shared=False))

    def row(times: DataFrame, name: str, rate: float, explored: float, value: float, target: float) -> DataFrame:
        return X.compared(times, name).withColumns({"rate": F.lit(rate), "explored": F.lit(explored), "best": F.lit(value), "target": F.lit(target)})

    m4 = X.curves(g4, _vectors(s, d), 10, tuners.rungs(4, 15, 120))
    rate4, target4 = M.merge_rate(g4).first()["rate"], first(g4, _vectors(s, d), 10, [120])
    times, decisions = X.halving_study(g4, m4, 4, 15, 120, WORKERS, EXTRA)
    last = m4.join(decisions.where("action = 'finish'"), ["study", "trial"], "left_semi").where("step = 120")
    out = [row(times, "halving", rate4, X.explored(g4, X.last_steps(decisions)), best(last), target4)]
    times, reached = X.async_study(g4, m4, 4, 15, 120, WORKERS, EXTRA)
    stage = reached.where("way = 'stage'").drop("way")
    out.append(row(times, "async halving", rate4, X.explored(g4, stage), best(m4.join(stage, ["study", "trial", "step"], "left_semi")), target4))
    for name, g, model, source, classes, measure, end, extra, workers, iteration in (
        ("grid cutout", g6, training.OneHidden, _vectors, 10, "value", 120, EXTRA, WORKERS, 8), ("grid length", g7, training.WordBag, _texts, 2, "f1", 270, 0.0, WORKERS // 4, 1),
    ):
        rate, told = M.merge_rate(g).first()["rate"], (source(s, d), classes, [end], model, measure, iteration)
        out.append(row(X.grid_study(g, workers, extra), name, rate, rate, best(X.curves(g, *told)), first(g, *told)))
    return reduce(DataFrame.unionByName, out)


def _multi(s: SparkSession, d: str, low: bool) -> DataFrame:
    """One to eight studies of 144 trials at once on one cluster: (workload, way, worker_time, makespan, ratios, transitions, rate)."""
    out = []
    for k in (1, 2, 4, 8):
        g = T.canonical((space.w9 if low else space.w8)(s, k))
        out.append(X.compared(X.grid_study(g, WORKERS, 0.0), f"S{k}").withColumn("rate", F.lit(M.merge_rate(g).first()["rate"])))
    return reduce(DataFrame.unionByName, out)


_register("table_single")(_single)
_register("table_multi_high")(lambda s, d: _multi(s, d, False))
_register("table_multi_low")(lambda s, d: _multi(s, d, True))


# worker time of the grids that parts name, counted step by step: all steps for the ways without sharing, different ones with it
_register("grid_work", f"""with lr as (select distinct p_type, cast(p_size as bigint) as m from part where p_type is not null and p_size is not null),
bs as (select distinct p_type, b from (select p_type, try_cast(regexp_extract(p_brand, '([0-9]+)$', 1) as bigint) as b from part) where p_type is not null and b is not null),
ep as (select unnest(range(0, 120)) as step),
lh as (select p_type, m, step, md5(string_agg(case when step < m then '0.1' when step < m + 60 then '0.01' else '0.001' end, '|') over (partition by p_type, m order by step rows unbounded preceding)) as h from lr, ep),
bh as (select p_type, b, step, md5(string_agg(case when step < 20 + 4 * b then '128' else '256' end, '|') over (partition by p_type, b order by step rows unbounded preceding)) as h from bs, ep),
hist as (select p_type, step, lh.h || bh.h as h from lh join bh using (p_type, step))
select p_type as workload, way, cast(case when way = 'stage' then count(distinct step || h) else count(*) end + {EXTRA} as double) as worker_time from hist, (values ('external'), ('trial'), ('stage')) as w(way) group by p_type, way""")(
    lambda s, d: X.grid_studies(T.canonical(space.of_parts(A.table(s, d, "part"))), WORKERS, EXTRA).select(F.unhex("study").cast("string").alias("workload"), "way", "worker_time")
)
_register("placements_fig", "select * from (values (2, 400.0::double, 700.0::double, 3), (99, 300.0::double, 700.0::double, 3)) as t(w, makespan, worker_time, transitions)")(lambda s, d: _placed(s))


def _placed(s: SparkSession) -> DataFrame:
    """The four trials of the figure on two workers and on many: end-to-end time, time workers were held, checkpoints loaded."""
    g = literal(s, _FOUR)
    own, out = X.chains_of(g, "stage").withColumn("study", F.lit("fig")), []
    for w in (2, 99):
        p = simulate.placements(own, "chains", w)
        out.append(M.makespan(p, ("study",)).join(M.transitions(p, ("study",)), "study").select(F.lit(w).alias("w"), "makespan", "worker_time", "transitions"))
    return out[0].unionByName(out[1])


# --- streams ------------------------------------------------------------------------------

LATE = "40 days"


def _stream(s: SparkSession, d: str) -> DataFrame:
    # a file source reads folders and patterns, not the name of one file
    return reports.source(s, f"{d}/event[s].parquet", s.read.parquet(f"{d}/events.parquet").schema)


_register("stream_tumbling", "select time_bucket(interval 1 day, ts) as window_start, event_type, count(*) as n, max(value) as best from events group by all")(lambda s, d: reports.collected(reports.tumbling(_stream(s, d), "1 day", LATE)).withColumn("window_start", F.col("window_start").cast("timestamp_ntz")))
_register("stream_dedup", "select event_id, event_type from events")(lambda s, d: reports.collected(reports.deduplicated(_stream(s, d), ["event_id"], LATE).select("event_id", "event_type"), "append"))
_register("stream_enrich", "select event_id, c_mktsegment from events join customer on user_id = c_custkey")(
    lambda s, d: reports.collected(reports.enriched(_stream(s, d), A.table(s, d, "customer").select(F.col("c_custkey").alias("user_id"), "c_mktsegment"), "user_id").select("event_id", "c_mktsegment"), "append")
)
_register("stream_interval_join", "select a.event_id, b.event_id as later_id from events a join events b on a.user_id = b.user_id and b.ts > a.ts and b.ts <= a.ts + interval 1 hour where a.event_type = 'signup' and b.event_type = 'purchase'")(
    lambda s, d: reports.collected(reports.followed(_stream(s, d).where("event_type = 'signup'"), _stream(s, d).where("event_type = 'purchase'"), "1 hour", LATE).select("event_id", "later_id"), "append")
)
_register("stream_session", "select user_id, min(ts) as session_start, count(*) as n from (select *, sum(f) over (partition by user_id order by ts, event_id rows unbounded preceding) as island from (select *, case when ts - lag(ts) over (partition by user_id order by ts, event_id) <= interval 6 hour then 0 else 1 end as f from events)) group by user_id, island")(
    lambda s, d: reports.collected(reports.sessions(_stream(s, d), "6 hours", LATE)).withColumn("session_start", F.col("session_start").cast("timestamp_ntz"))
)
_register("stream_sliding", "select time_bucket(interval 1 day, ts) - to_days(back) as window_start, count(*) as n, max(value) as best from events, (values (0), (1)) as b(back) group by all")(
    lambda s, d: reports.collected(reports.sliding(_stream(s, d), "2 days", "1 day", LATE)).withColumn("window_start", F.col("window_start").cast("timestamp_ntz"))
)


def _stream_asha(s: SparkSession, d: str) -> DataFrame:
    """The replay of ``asha_replay`` fed by the stream: the k-th report of a user is that of step k."""
    ord_ = F.concat(F.date_format("ts", "yyyyMMddHHmmss.SSSSSS"), F.format_string("-%020d", F.col("event_id")))
    study, trial = F.concat(F.lit("s"), (F.col("user_id") % 2).cast("string")).alias("study"), F.col("user_id").cast("long").alias("trial")
    shaped = _stream(s, d).select(study, ord_.alias("ord"), trial, F.lit(0).cast("long").alias("step"), "value")
    return reports.collected(reports.async_promotions(shaped, 4, [2, 8, 32], counted=True), "append")


_register("stream_asha")(_stream_asha)


def _stream_late(s: SparkSession, d: str) -> DataFrame:
    """Daily counts of reports that come in three files, the newest third first: (kept, late, told).

    The oldest third comes after the watermark has passed: its reports are counted, not lost unseen; ``told``: the stream's progress says so.
    """
    rows, scratch = s.read.parquet(f"{d}/events.parquet"), Scratch(s, "late")
    when = F.unix_micros(F.col("ts").cast("timestamp")).cast("double")
    third = rows.select(when.alias("at")).stat.approxQuantile("at", [1 / 3, 2 / 3], 0.0)
    for k, part in enumerate((when > third[1], (when <= third[1]) & (when > third[0]), when <= third[0])):
        rows.where(part).coalesce(1).write.parquet(f"{scratch.root}/in/{k}")
    base = s.readStream.schema(rows.schema).option("maxFilesPerTrigger", 1).option("recursiveFileLookup", "true").parquet(f"{scratch.root}/in")
    told, dropped = reports.followed_progress(reports.tumbling(base.withColumn("ts", F.col("ts").cast("timestamp")), "1 day", "1 day"), "update")
    last = told.groupBy("window_start", "event_type").agg(F.max("n").alias("n")).agg(F.coalesce(F.sum("n"), F.lit(0)).alias("kept"))
    return last.select("kept", (F.lit(rows.count()) - F.col("kept")).alias("late"), F.lit(dropped > 0).alias("told"))


_register("stream_late", "select count(*) filter (where n > 1) as kept, count(*) filter (where n = 1) as late, true as told from (select ntile(3) over (order by ts) as n from events)")(_stream_late)

_register("stream_reports", "select path, step, arg_max(value, (ts, event_id)) as value from (select cast(user_id as varchar) as path, cast(json_extract(props, '$.k') as bigint) as step, ts, event_id, value from events) group by path, step")(lambda s, d: _stream_reports(s, d))


def _stream_reports(s: SparkSession, d: str) -> DataFrame:
    """The event stream as workers' reports, folded into a plan's metrics: the last report of each node and step."""
    store = PlanStore(s, Scratch(s, "reports").root, "events")
    base = _stream(s, d).select(F.col("user_id").cast("string").alias("path"), F.from_json("props", "k bigint")["k"].alias("step"), F.struct("ts", "event_id").alias("ord"), "value")
    reports.aggregate(base, store, lambda n: None)
    return store.read("metrics")


# --- further functions --------------------------------------------------------------------

_register("plan_refcounts", seg_sql("orders") + _NODES + "select path, start, count(*) as refs from seg group by path, start")(lambda s, d: T.nodes(seg(s, d, "orders")).select("path", "start", "refs"))
_register("range_metric", "select event_id, count(*) over w as n, round(max(value) over w, 6) as best from events window w as (partition by user_id order by ts range between interval 1 day preceding and current row)")(
    lambda s, d: A.table(s, d, "events").withColumn("at", F.unix_micros(F.col("ts").cast("timestamp"))).select(
        "event_id", F.count("*").over(w := Window.partitionBy("user_id").orderBy("at").rangeBetween(-86_400_000_000, 0)).alias("n"), F.round(F.max("value").over(w), 6).alias("best")
    )
)
_register("vector_dot", "select vec_id, round(list_sum(list_transform(embedding, lambda x: cast(x as double) * cast(x as double))), 4) as dot from embeddings")(
    lambda s, d: A.table(s, d, "embeddings").select("vec_id", F.round(F.aggregate("embedding", F.lit(0.0), lambda a, x: a + x.cast("double") * x.cast("double")), 4).alias("dot"))
)
_SPECS = ["constant(0.1)", "exponential(0.1,0.95)", "linear(0.1,0,100)"]
_register("parse_specs", "select spec, regexp_extract(spec, '^([a-z]+)', 1) as fn, cast(len(string_split(spec, ',')) as bigint) as n_args, cast(regexp_extract(spec, '[(]([0-9.]+)', 1) as double) as first_arg from (values " + ", ".join(f"('{x}')" for x in _SPECS) + ") t(spec)")(
    lambda s, d: s.createDataFrame([(x,) for x in _SPECS], "spec string").select(
        "spec", F.regexp_extract("spec", "^([a-z]+)", 1).alias("fn"), F.size(F.split("spec", ",")).cast("long").alias("n_args"), F.regexp_extract("spec", "[(]([0-9.]+)", 1).cast("double").alias("first_arg")
    )
)
_register("udf_hp_value", "select step, round(0.1 * pow(0.95, step), 9) as value from (select unnest(range(0, 100)) as step)")(
    lambda s, d: s.range(100).select(F.col("id").alias("step"), F.round(H.value_udf()(F.lit("exponential(0.1,0.95)"), F.col("id")), 9).alias("value"))
)


def _sql_surface(s: SparkSession, d: str) -> DataFrame:
    seg(s, d, "orders").createOrReplaceTempView("segments")
    return s.sql("select cast(depth as bigint) as depth, count(*) as segments, count(distinct path) as nodes from segments group by depth")


def _udtf_expand(s: SparkSession, d: str) -> DataFrame:
    seg(s, d, "orders").createOrReplaceTempView("segments")
    s.udtf.register("expand_range", T.expand_udtf())
    return s.sql("select trial, step, cfg from segments, lateral expand_range(segments.start, segments.end)")


_register("sql_surface", seg_sql("orders") + "select cast(k as bigint) as depth, count(*) as segments, count(distinct path) as nodes from seg group by k")(_sql_surface)
_register("udtf_expand", seg_sql("orders") + "select trial, cast(step as bigint) as step, cfg from (select trial, cfg, unnest(range(start, end_)) as step from seg)")(_udtf_expand)
_register("ckpt_map", seg_sql("orders") + _CK + ", steps as (select path, step from ck) select path, count(*) as n, cast(max(step) as bigint) as latest from steps group by path")(
    lambda s, d: _ckpts(seg(s, d, "orders")).groupBy("path").agg(F.map_from_entries(F.collect_list(F.struct("step", F.sha2(F.col("path").cast("binary"), 256)))).alias("files"))
    .select("path", F.size("files").cast("long").alias("n"), F.array_max(F.map_keys("files")).alias("latest"))
)


def _sink(s: SparkSession, d: str) -> DataFrame:
    """Nodes of the plan written by two submissions, compacted, and read again."""
    g = seg(s, d, "orders")
    store = PlanStore(s, Scratch(s, "sink").root, "orders")
    for part in (0, 1):
        own = g.where(F.col("trial") % 2 == part)
        new = plan.plan_nodes(own).join(store.read("nodes").select("path"), "path", "left_anti")
        store.append("nodes", new.join(T.lines(own), "path"), f"submission-{part}")
    store.compact("nodes")
    return store.read("nodes").select("path", "parent", "start", F.col("depth").cast("long").alias("depth"), F.size("line").cast("long").alias("line"))


_register("plan_sink", seg_sql("orders") + _NODES + "select path, parent, start, depth, depth + 1 as line from nodes")(_sink)
_register("release_ckpts", seg_sql("orders") + _NODES + _CK + "select ck.path, ck.step from ck where not exists (select 1 from seg where trial % 5 <> 0 and seg.path = ck.path and seg.end_ >= ck.step)")(
    lambda s, d: plan.unneeded(_ckpts(g := seg(s, d, "orders")), plan.trial_requests(g), T.lines(g), g.where("trial % 5 = 0").select("study", "trial").distinct())
)
_register("scan_trials", seg_sql("conversations") + "select trial, count(*) as segments, cast(max(end_) as bigint) as steps from seg group by trial")(lambda s, d: _scanned(s, d))


def _scanned(s: SparkSession, d: str) -> DataFrame:
    """Trials from JSON files as clients leave them: the conversations, written out first."""
    root = Scratch(s, "files").root
    p = A.conversations(s, d)
    order = F.row_number().over(Window.partitionBy("study", "trial").orderBy("ord"))
    p.select("study", "trial", order.cast("long").alias("ord"), "cfg", "steps").write.json(f"{root}/trials")
    return T.canonical(A.trial_files(s, f"{root}/trials")).groupBy("trial").agg(F.count("*").alias("segments"), F.max("end").alias("steps"))


_register("udaf_auc", "select lang, round((sum(case when quality = 1 then r end) - n1 * (n1 + 1) / 2) / nullif(n1 * n0, 0), 9) as auc from (select lang, quality, rank() over w + (count(*) over (partition by lang, n_chars) - 1) / 2 as r, count(*) filter (where quality = 1) over (partition by lang) as n1, count(*) filter (where quality <> 1) over (partition by lang) as n0 from documents join labels using (doc_id) where quality is not null window w as (partition by lang order by n_chars)) group by lang, n1, n0")(
    lambda s, d: A.table(s, d, "documents").select("doc_id", "lang", "n_chars").join(A.table(s, d, "labels").select("doc_id", "quality").where("quality is not null"), "doc_id").groupBy("lang").agg(F.round(M.auc_udaf()("n_chars", "quality"), 9).alias("auc"))
)
_register("tune_sampled")(lambda s, d: _tuned(s, d, study.sampled(4, 64)).select("trial", "rung", "rank", "action", "value"))
_register("tune_adaptive")(lambda s, d: _tuned(s, d, study.adaptive(3, 3, 48, 64)).select("round", "trial", "rank", "value"))
_register("study_asha")(lambda s, d: _single_async(s, d))


def _single_async(s: SparkSession, d: str) -> DataFrame:
    """Asynchronous halving over the 448 trials on forty workers: what each way reached and what it cost."""
    g = T.canonical(space.w4(s))
    m = X.curves(g, _vectors(s, d), 10, tuners.rungs(4, 15, 120))
    times, reached = X.async_study(g, m, 4, 15, 120, WORKERS, EXTRA)
    best = reached.join(m, ["study", "trial", "step"]).groupBy("way").agg(F.count("*").alias("trials"), F.count_if(F.col("step") == 120).alias("finished"), F.max("value").alias("best"))
    return times.join(best, "way")


_CONSTANT, _NUMBERS = "format('constant({:.12g})', l_discount)", [f"format('{{:.12g}}', {x})" for x in ("l_discount", "l_tax", "l_quantity", "round(1 - l_tax, 2)")]
_register("hp_normalise", f"""select fn, canonical, count(*) as specs from (
select 'exponential' as fn, case when round(1 - l_tax, 2) = 1 then {_CONSTANT} else 'exponential(' || {_NUMBERS[0]} || ',' || {_NUMBERS[3]} || ')' end as canonical from lineitem
union all select 'linear', case when l_discount = l_tax and l_quantity is not null then {_CONSTANT} else 'linear(' || {_NUMBERS[0]} || ',' || {_NUMBERS[1]} || ',' || {_NUMBERS[2]} || ')' end from lineitem
union all select 'cosine', case when l_discount = l_tax and l_quantity is not null then {_CONSTANT} else 'cosine(' || {_NUMBERS[0]} || ',' || {_NUMBERS[2]} || ',' || {_NUMBERS[1]} || ')' end from lineitem) group by fn, canonical""")(lambda s, d: _normalised(s, d))


def _normalised(s: SparkSession, d: str) -> DataFrame:
    """Canonical texts of the settings that order lines spell (discount: first value, tax: decay or last value, quantity: steps), and how many lines spell each."""
    start, end, steps = (F.col(x) for x in ("l_discount", "l_tax", "l_quantity"))
    spelt = [("exponential", (start, F.round(1 - end, 2))), ("linear", (start, end, steps)), ("cosine", (start, steps, end))]
    lines = A.table(s, d, "lineitem").groupBy("l_discount", "l_tax", "l_quantity").agg(F.count("*").alias("n"))
    specs = lines.select("n", F.explode(F.array(*[F.struct(F.lit(fn).alias("fn"), F.array(*args).alias("args")) for fn, args in spelt])).alias("x")).select("n", "x.*")
    return specs.select("fn", H.text_udf()("fn", "args").alias("canonical"), "n").groupBy("fn", "canonical").agg(F.sum("n").alias("specs"))
