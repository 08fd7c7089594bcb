"""Registry: a query for each method, variant, baseline, measure and operator, and SQL for those that SQL can express."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from farfield.algorithms import programs as P
from farfield.algorithms import run as R
from farfield.baselines import handwritten as H
from farfield.lang import dsl as L
from farfield.lang.dsl import In, Nbr, Out, either, foreign, local, remote, step, stop, var, when
from farfield.lang.dsl import F as V
from farfield.operators import relational as O
from farfield.plans.knowledge import Knows, plan_reads
from farfield.plans.runtime import run
from farfield.plans.store import let_workers_import, materialise
from farfield.sources import builders as B
from farfield.sources.graph import Graph, intern_ids
from farfield.sources.tables import load
from farfield.streaming import stream as S

QUERIES: dict = {}
ORACLES: dict = {}


def query(name: str, sql: str | None = None):
    def put(fn):
        QUERIES[name] = fn
        if sql:
            ORACLES[name] = sql
        return fn

    return put


# --- SQL of the graphs ---

EVENTS = "ev AS (SELECT event_id AS id, user_id, ts, CAST(round(value * 100) AS BIGINT) AS v FROM events)"
LINES = "SELECT {k} AS src, lead({k}) OVER w AS dst, CAST(l_quantity AS BIGINT) AS q FROM lineitem WHERE {f} WINDOW w AS (PARTITION BY l_orderkey ORDER BY l_linenumber, l_partkey, l_suppkey, l_quantity, l_extendedprice)"


def flow(which: str) -> str:
    return f"ln AS ({LINES.format(k='l_partkey', f=B.LINE_FILTERS[which])}), e AS (SELECT src, dst, min(q) AS val FROM ln WHERE dst IS NOT NULL AND src <> dst GROUP BY src, dst), v AS (SELECT p_partkey AS id FROM part)"


BOTH = "b AS (SELECT src, dst FROM e UNION SELECT dst, src FROM e)"
MESH = f"ln AS ({LINES.format(k='l_suppkey', f=B.LINE_FILTERS['c'])}), n AS (SELECT least(src, dst) AS src, greatest(src, dst) AS dst, count(*) AS n FROM ln WHERE dst IS NOT NULL AND src <> dst GROUP BY 1, 2), e AS (SELECT src, dst, row_number() OVER (ORDER BY n DESC, src, dst) AS val FROM n)"
OVERLAP = "l AS (SELECT DISTINCT doc_id, md5(trim(x)) AS k FROM (SELECT doc_id, unnest(string_split(text, chr(10))) AS x FROM documents) WHERE length(trim(x)) >= 40), m AS (SELECT k, min(doc_id) AS dst FROM l GROUP BY k), e AS (SELECT DISTINCT doc_id AS src, dst FROM l JOIN m USING (k) WHERE doc_id > dst), v AS (SELECT doc_id AS id FROM documents)"
LINKS = """l AS (SELECT DISTINCT page_id, unnest(regexp_extract_all(html, 'href="([^"]*)"', 1)) AS h FROM pages), m AS (SELECT h, min(page_id) AS dst FROM l GROUP BY h), e AS (SELECT DISTINCT page_id AS src, dst, 1 AS val FROM l JOIN m USING (h) WHERE page_id <> dst), v AS (SELECT page_id AS id FROM pages)"""


def labels_sql(graph: str, out: str = "comp") -> str:
    return f"""WITH RECURSIVE {graph}, {BOTH}, cc(id, comp) USING KEY (id) AS (
      SELECT id, id FROM v
      UNION
      SELECT b.dst, min(c.comp) FROM cc c JOIN b ON b.src = c.id JOIN recurring.cc r ON r.id = b.dst WHERE c.comp < r.comp GROUP BY b.dst
    ) SELECT id, comp AS {out} FROM cc"""


def dist_sql(graph: str, length: str = "e.val") -> str:
    return f"""WITH RECURSIVE {graph}, sp(id, dist) USING KEY (id) AS (
      SELECT CAST(0 AS BIGINT), CAST(0 AS BIGINT)
      UNION
      SELECT e.dst, min(s.dist + {length}) FROM sp s JOIN e ON e.src = s.id LEFT JOIN recurring.sp r ON r.id = e.dst
      WHERE r.dist IS NULL OR s.dist + {length} < r.dist GROUP BY e.dst
    ) SELECT v.id, sp.dist FROM v LEFT JOIN sp ON v.id = sp.id"""


def rank_sql(items: str, order: str, by: str, head: str) -> str:
    over = f"OVER ({by} ORDER BY {order} ROWS UNBOUNDED PRECEDING)"
    return f"WITH t AS ({items}) SELECT id, CAST(sum(v) {over} AS BIGINT) AS rank FROM t UNION ALL SELECT DISTINCT {head}, CAST(0 AS BIGINT) FROM t"


def pagerank_sql(graph: str, k: int) -> str:
    return f"""WITH RECURSIVE {graph}, d AS (SELECT src, count(*) AS d FROM e GROUP BY src), n AS (SELECT count(*) AS n FROM v), pr(k, id, rank) AS (
      SELECT 0, id, 1.0::DOUBLE / n FROM v, n
      UNION ALL
      SELECT k + 1, v.id, 0.15 / n.n + 0.85 * coalesce(sum(x.r), 0)
      FROM v CROSS JOIN n CROSS JOIN (SELECT DISTINCT k FROM pr) kk LEFT JOIN (SELECT e.dst, pr.rank / d.d AS r FROM pr JOIN e ON e.src = pr.id JOIN d ON d.src = e.src) x ON x.dst = v.id
      WHERE k < {k} GROUP BY k, v.id, n.n
    ) SELECT id, round(rank, 9) AS rank FROM pr WHERE k = {k}"""


SCC_SQL = f"""WITH RECURSIVE {flow('c')}, reach(a, b) AS (SELECT id, id FROM v UNION SELECT r.a, e.dst FROM reach r JOIN e ON e.src = r.b)
SELECT x.a AS id, min(x.b) AS scc FROM reach x JOIN reach y ON x.a = y.b AND x.b = y.a GROUP BY x.a"""
MSF_SQL = f"""WITH RECURSIVE {MESH}, b AS (SELECT src, dst, val FROM e UNION ALL SELECT dst, src, val FROM e),
mm(a, z, w) USING KEY (a, z) AS (
  SELECT src, dst, val FROM b
  UNION
  SELECT m.a, b.dst, min(greatest(m.w, b.val)) FROM mm m JOIN b ON b.src = m.z LEFT JOIN recurring.mm r ON r.a = m.a AND r.z = b.dst
  WHERE m.a <> b.dst AND (r.w IS NULL OR greatest(m.w, b.val) < r.w) GROUP BY m.a, b.dst
) SELECT e.src, e.dst, e.val FROM e JOIN mm ON mm.a = e.src AND mm.z = e.dst WHERE mm.w >= e.val"""
FOREST_SQL = """f AS (SELECT CAST(r_regionkey AS BIGINT) AS id, CAST(r_regionkey AS BIGINT) AS p FROM region
 UNION ALL SELECT 1000 + n_nationkey, n_regionkey FROM nation UNION ALL SELECT 10000000000 + s_suppkey, 1000 + s_nationkey FROM supplier
 UNION ALL SELECT 20000000000 + c_custkey, 1000 + c_nationkey FROM customer UNION ALL SELECT 30000000000 + o_orderkey, 20000000000 + o_custkey FROM orders)"""

# --- chains ---

for _d in (2, 3, 4, 5, 6, 7, 8):  # by the messages of the read plan
    _sql = f"WITH {EVENTS} SELECT id, coalesce(lag(id, {_d}) OVER (ORDER BY ts, id), -1) AS value FROM ev UNION ALL SELECT -1, -1"
    query(f"chain_depth{_d}_event_chain", _sql)(lambda s, d, k=_d: run(P.chain(("Pred",) * k), B.event_chain(s, d)).select(F.col("Value").alias("value")))


_chain_by = lambda reads, path, build: lambda s, d: run(P.chain(path), build(s, d), reads=reads).select(F.col("Value").alias("value"))
for _d in (4, 8):
    for _reads in ("doubling", "request_reply"):
        query(f"chain_{_reads}_depth{_d}", ORACLES[f"chain_depth{_d}_event_chain"])(_chain_by(_reads, ("Pred",) * _d, B.event_chain))


@query("chain_mixed_region_of_order", "SELECT 30000000000 + o_orderkey AS id, r_name AS value FROM orders JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey")
def chain_mixed(s, d):
    return run(P.chain(("Cust", "Nation", "Region", "Name")), B.geo_forest(s, d)).state.filter("Kind = 'orders' AND Value IS NOT NULL").select("id", F.col("Value").alias("value"))


@query("computed_index_read", f"WITH {EVENTS}, r AS (SELECT id, v, lag(id) OVER (ORDER BY ts, id) AS p FROM ev) SELECT r.id, (SELECT v FROM ev WHERE ev.id = r.id - 1) AS value FROM r UNION ALL SELECT -1, NULL")
def computed_index(s, d):
    return run(step(lambda u: [local(V.Value[u], V.Val[V.id[u] - 1])]), Graph(B.event_chain(s, d).vertices.withColumn("Val", F.when(F.col("id") >= 0, F.col("Val"))))).select(F.col("Value").alias("value"))


# --- writes, neighbourhoods, steps ---


@query("remote_customer_totals", """SELECT 20000000000 + c_custkey AS id, coalesce(sum(a), 0)::BIGINT AS total, min(a) AS lo, coalesce(max(a), 0) AS hi, coalesce(bool_or(a > 30000000), false) AS any, coalesce(bool_and(a > 100000), true) AS every
FROM customer LEFT JOIN (SELECT o_custkey, CAST(round(o_totalprice * 100) AS BIGINT) AS a FROM orders) ON o_custkey = c_custkey GROUP BY c_custkey""")
def remote_totals(s, d):
    p = step(lambda u: [local(V.Total[u], 0), local(V.Lo[u], L.inf), local(V.Hi[u], 0), local(V.Any[u], False), local(V.Every[u], True)]) >> step(lambda u: [
        when(V.Amount[u].ne(L.inf), [
            remote(V.Total[V.Cust[u]], "+", V.Amount[u]), remote(V.Lo[V.Cust[u]], "min", V.Amount[u]), remote(V.Hi[V.Cust[u]], "max", V.Amount[u]),
            remote(V.Any[V.Cust[u]], "or", V.Amount[u] > 30_000_000), remote(V.Every[V.Cust[u]], "and", V.Amount[u] > 100_000),
        ])
    ])
    g = B.geo_forest(s, d)
    g = Graph(g.vertices.withColumn("Lo", F.lit(None).cast("long")))
    out = run(p, g).state.filter("Kind = 'customer'")
    return out.select("id", F.col("Total").alias("total"), F.col("Lo").alias("lo"), F.col("Hi").alias("hi"), F.col("Any").alias("any"), F.col("Every").alias("every"))


for _f, _agg in (("minimum", "min(val)"), ("maximum", "max(val)"), ("total", "coalesce(sum(val), 0)::BIGINT"), ("count", "count(val)")):
    for _side, _end in (("In", "dst"), ("Out", "src")):
        _fn = lambda s, d, f=_f, e={"In": In, "Out": Out}[_side]: run(step(lambda u: [local(V.X[u], getattr(e[u], f)(lambda x: x.val) if f != "count" else e[u].count())]), B.part_flow(s, d, "b")).select(F.col("X").alias("x"))
        query(f"neighbour_{_f}_{_side.lower()}_part_flow", f"WITH {flow('b')} SELECT id, {_agg} AS x FROM v LEFT JOIN e ON e.{_end} = v.id GROUP BY id")(_fn)


@query("neighbour_filtered_part_flow", f"WITH {flow('b')} SELECT v.id, min(e.src + e.val) AS x, count(CASE WHEN e.src < v.id THEN 1 END) AS below FROM v LEFT JOIN e ON e.dst = v.id AND e.src % 3 = 0 GROUP BY v.id")
def neighbour_filtered(s, d):
    g = B.part_flow(s, d, "b")
    g = Graph(g.vertices.withColumn("A", F.col("id") % 3 == 0), g.edges)
    p = step(lambda u: [
        local(V.X[u], In[u].where(lambda e: V.A[e.ref]).minimum(lambda e: V.id[e.ref] + e.val)),
        local(V.Below[u], In[u].where(lambda e: V.A[e.ref], lambda e: V.id[e.ref] < V.id[u]).count()),
    ])
    return run(p, g).select(F.col("X").alias("x"), F.col("Below").cast("long").alias("below"))


@query("neighbour_chain_part_flow", f"WITH {flow('b')} SELECT v.id, max(e.src // 4) AS x FROM v LEFT JOIN e ON e.dst = v.id GROUP BY v.id")
def neighbour_chain(s, d):
    """A chain of two fields at the neighbour."""
    g = B.part_flow(s, d, "b")
    g = Graph(g.vertices.withColumn("H", F.floor(F.col("id") / 2).cast("long")), g.edges)
    return run(step(lambda u: [local(V.X[u], In[u].maximum(lambda e: V.H[V.H[e.ref]]))]), g).select(F.col("X").alias("x"))


@query("for_edge_remote_part_flow", f"WITH {flow('b')} SELECT v.id, coalesce(sum(e.val * 2), 0)::BIGINT AS x, count(e.src) AS n FROM v LEFT JOIN e ON e.dst = v.id GROUP BY v.id")
def for_edge_remote(s, d):
    """A loop over edges out with a write at each end, and one that accumulates here."""
    p = step(lambda u: [local(V.X[u], 0), local(V.N[u], 0)]) >> step(lambda u: [
        L.for_edge(Out[u], lambda e: [remote(V.X[e.ref], "+", e.val * 2)]), L.for_edge(In[u], lambda e: [local(V.N[u], 1, "+")]),
    ])
    return run(p, B.part_flow(s, d, "b")).select(F.col("X").alias("x"), F.col("N").alias("n"))


@query("local_branching_step", "SELECT p_partkey AS id, CASE WHEN p_partkey % 2 = 0 THEN p_partkey * 3 WHEN p_partkey > 100 THEN p_partkey - 100 ELSE -p_partkey END AS x FROM part")
def local_branching(s, d):
    p = step(lambda u: [when(V.Even[u], [local(V.X[u], V.id[u] * 3)], [local(V.X[u], either(V.id[u] > 100, V.id[u] - 100, -V.id[u]))])])
    g = B.part_flow(s, d, "b")
    return run(p, Graph(g.vertices.withColumn("Even", F.col("id") % 2 == 0))).select(F.col("X").alias("x"))


@query("stop_frozen_fields", f"WITH {EVENTS}, r AS (SELECT id, v, lag(v) OVER (ORDER BY ts, id) AS pv FROM ev) SELECT id, CASE WHEN v % 2 = 0 THEN v ELSE v + coalesce(pv, 0) END AS x FROM r UNION ALL SELECT -1, 0")
def stop_frozen(s, d):
    """Those with even values stop: they change no more, but are still read."""
    g = Graph(B.event_chain(s, d).vertices.withColumn("Even", F.col("Val") % 2 == 0))
    p = step(lambda u: [local(V.X[u], V.Val[u])]) >> stop(lambda u: V.Even[u]) >> step(lambda u: [local(V.X[u], V.X[u] + V.X[V.Pred[u]])])
    return run(p, g).select(F.col("X").alias("x"))


@query("foreign_function_step", "SELECT p_partkey AS id, upper(p_name) || '/' || p_brand AS x FROM part")
def foreign_step(s, d):
    p = step(lambda u: [local(V.X[u], foreign("label", V.Name[u], V.Brand[u]))])
    return run(p, B.part_flow(s, d, "b"), functions={"label": lambda a, b: F.concat_ws("/", F.upper(a), b)}).select(F.col("X").alias("x"))


_MUTUAL = f"WITH {flow('b')}, p AS (SELECT src, min(dst) AS t FROM e GROUP BY src) SELECT a.src AS id FROM p a JOIN p b ON a.t = b.src AND b.t = a.src"
_pointer = lambda s, d: run(step(lambda u: [local(V.D[u], Out[u].minimum(lambda e: V.id[e.ref]))]), B.part_flow(s, d, "b")).select("D")
query("mutual_pairs_part_flow", _MUTUAL)(lambda s, d: R.mutual_pointers(_pointer(s, d), True))
query("mutual_pairs_two_rounds", _MUTUAL)(lambda s, d: R.mutual_pointers(_pointer(s, d), False))
_back = step(lambda u: [local(V.D[u], Out[u].minimum(lambda e: V.id[e.ref]))]) >> step(lambda u: [local(V.Hit[u], V.D[V.D[u]].eq(V.id[u]))])
for _way in (True, False):
    query(f"mutual_pairs_rewrite_{'on' if _way else 'off'}", _MUTUAL)(lambda s, d, w=_way: run(_back, B.part_flow(s, d, "b"), peephole=w).state.filter("Hit").select("id"))


@query("two_hop_part_flow", f"WITH {flow('b')}, n AS (SELECT src, max(val) AS m FROM e GROUP BY src) SELECT v.id, coalesce(sum(n.m), 0)::BIGINT AS x FROM v LEFT JOIN e ON e.src = v.id LEFT JOIN n ON n.src = e.dst GROUP BY v.id")
def two_hop(s, d):
    """A comprehension inside another."""
    p = step(lambda u: [local(V.X[u], Out[u].total(lambda e: either(Out[e.ref].maximum(lambda f: f.val, "f").eq(L.inf), 0, Out[e.ref].maximum(lambda f: f.val, "f")), "e"))])
    return run(p, B.part_flow(s, d, "b"), allow_two_hop=True).select(F.col("X").alias("x"))

# --- algorithms and their variants ---

_dist = lambda r: r.select(F.col("D").alias("dist"))
_comp = lambda r: r.select(F.col("D").alias("comp"))
_rank = lambda r: r.select(F.col("Sum").alias("rank"))
_pr = lambda df: df.select("id", F.round("rank", 9).alias("rank"))
_sp = dist_sql(flow("b"))
query("sssp_part_flow", _sp)(lambda s, d: _dist(R.sssp(B.part_flow(s, d, "b"))))
query("sssp_unit_part_flow", dist_sql(flow("b"), "1"))(lambda s, d: _dist(R.sssp(B.part_flow(s, d, "b"), unit=True)))
query("sssp_no_active_flags", _sp)(lambda s, d: _dist(R.sssp(B.part_flow(s, d, "b"), active=False)))
query("sssp_no_combiner", _sp)(lambda s, d: _dist(R.sssp(B.part_flow(s, d, "b"), combine=False)))
query("sssp_no_fuse", _sp)(lambda s, d: _dist(R.sssp(B.part_flow(s, d, "b"), fuse=False)))
query("hand_sssp", _sp)(lambda s, d: H.sssp(B.part_flow(s, d, "b"), frontier=False))
query("sssp_frontier", _sp)(lambda s, d: H.sssp(B.part_flow(s, d, "b"), frontier=True))

_cc, _ov = labels_sql(flow("c")), labels_sql(OVERLAP)
_exact = "SELECT doc_id AS id, min(doc_id) OVER (PARTITION BY md5(text)) AS comp FROM documents"
_users = "SELECT event_id AS id, min(event_id) OVER (PARTITION BY user_id) AS comp FROM events"
query("components_part_flow", _cc)(lambda s, d: _comp(R.components(B.undirected(B.part_flow(s, d, "c")))))
query("components_doc_overlap", _ov)(lambda s, d: _comp(R.components(B.doc_overlap(s, d))))
query("components_doc_exact", _exact)(lambda s, d: _comp(R.components(B.doc_exact(s, d))))
query("components_user_chain", _users)(lambda s, d: _comp(R.components(B.user_chain_graph(s, d))))
query("hashmin_part_flow", _cc)(lambda s, d: _comp(R.hashmin(B.undirected(B.part_flow(s, d, "c")))))
query("hashmin_doc_overlap", _ov)(lambda s, d: _comp(R.hashmin(B.doc_overlap(s, d))))
query("sv_no_merge", _exact)(lambda s, d: _comp(R.components(B.doc_exact(s, d), merge=False)))
query("sv_no_fuse", _exact)(lambda s, d: _comp(R.components(B.doc_exact(s, d), fuse=False)))
query("sv_no_merge_no_fuse", _exact)(lambda s, d: _comp(R.components(B.doc_exact(s, d), merge=False, fuse=False)))
query("sv_no_combiner", _exact)(lambda s, d: _comp(R.components(B.doc_exact(s, d), combine=False)))
query("hand_components", _cc)(lambda s, d: H.components(B.undirected(B.part_flow(s, d, "c"))))


@query("components_toxic_stopped", f"""WITH RECURSIVE {OVERLAP}, {BOTH}, x AS (SELECT v.id, coalesce(toxic, 0) = 1 AS gone FROM v LEFT JOIN labels ON doc_id = v.id), sv(k, id, d) AS (
  SELECT 0, id, id FROM v
  UNION ALL
  (WITH now AS (SELECT k, id, d FROM sv), near AS (SELECT b.src AS id, min(n.d) AS m FROM b JOIN now n ON n.id = b.dst GROUP BY b.src),
  seen AS (SELECT a.k, a.id, a.d, up.d AS g, near.m, x.gone FROM now a JOIN now up ON up.id = a.d JOIN x ON x.id = a.id LEFT JOIN near ON near.id = a.id),
  hook AS (SELECT d AS t, min(m) AS h FROM seen WHERE NOT gone AND g = d AND m < d GROUP BY d)
  SELECT k + 1, id, CASE WHEN gone THEN d ELSE least(CASE WHEN g = d THEN d ELSE g END, coalesce(h, 4611686018427387904)) END FROM seen LEFT JOIN hook ON t = id WHERE k < 25)
) SELECT id, d AS comp FROM sv WHERE k = 25""")
def components_stopped(s, d):
    """Toxic documents stop first: they keep their own label, which others still read."""
    p = P.components()
    return _comp(run(L.step(lambda u: [local(V.D[u], V.id[u])]) >> stop(lambda u: V.Toxic[u].eq(1)) >> p.parts[1], B.doc_overlap(s, d)))


_chain = f"SELECT event_id AS id, user_id, ts, CAST(round(value * 100) AS BIGINT) AS v FROM events"  # noqa: F541
query("list_rank_event_chain", rank_sql(_chain, "ts, id", "", "CAST(-1 AS BIGINT)"))(lambda s, d: _rank(R.list_rank(B.event_chain(s, d))))
_ur = rank_sql(_chain, "ts, id", "PARTITION BY user_id", "-(user_id + 1)")
query("list_rank_user_chains", _ur)(lambda s, d: _rank(R.list_rank(B.user_chains(s, d))))
query("list_rank_unit_user_chains", rank_sql(_chain.replace("CAST(round(value * 100) AS BIGINT)", "1"), "ts, id", "PARTITION BY user_id", "-(user_id + 1)"))(lambda s, d: _rank(R.list_rank(B.user_chains(s, d), val=1)))
query("list_rank_turn_chain", rank_sql("SELECT conv_id * 1000 + turn AS id, conv_id, turn, coalesce(length(text), 0) AS v FROM conversations", "turn", "PARTITION BY conv_id", "-(conv_id + 1)"))(lambda s, d: _rank(R.list_rank(B.turn_chain(s, d))))
query("list_rank_order_chain", rank_sql("SELECT o_orderkey AS id, o_custkey, o_orderdate, CAST(round(o_totalprice * 100) AS BIGINT) AS v FROM orders", "o_orderdate, id", "PARTITION BY o_custkey", "-(o_custkey + 1)"))(lambda s, d: _rank(R.list_rank(B.order_chain(s, d))))
query("lr_no_fuse", _ur)(lambda s, d: _rank(R.list_rank(B.user_chains(s, d), fuse=False)))
query("hand_list_rank", _ur)(lambda s, d: H.list_rank(B.user_chains(s, d)))
query("pagerank_part_flow", pagerank_sql(flow("a"), 10))(lambda s, d: _pr(R.pagerank(B.part_flow(s, d, "a"), 10).select(F.col("Rank").alias("rank"))))
query("pagerank_page_links", pagerank_sql(LINKS, 10))(lambda s, d: _pr(R.pagerank(B.page_links(s, d), 10).select(F.col("Rank").alias("rank"))))
def pagerank_more_sql(graph: str, k: int, lost: str, last: str) -> str:
    """lost: the rank of vertices without edges out is spread. last: which round is the answer."""
    return f"""WITH RECURSIVE {graph}, d AS (SELECT src, count(*) AS d FROM e GROUP BY src), n AS (SELECT count(*) AS n FROM v), pr(k, id, rank) AS (
      SELECT 0, id, 1.0::DOUBLE / n FROM v, n
      UNION ALL
      (WITH now AS (SELECT k, id, rank FROM pr), near AS (SELECT e.dst, sum(now.rank / d.d) AS r FROM now JOIN e ON e.src = now.id JOIN d ON d.src = e.src GROUP BY e.dst),
      l AS (SELECT {lost} AS lost FROM now LEFT JOIN d ON d.src = now.id WHERE d.d IS NULL)
      SELECT k + 1, now.id, 0.15 / n.n + 0.85 * (coalesce(r, 0) + coalesce(lost, 0) / n.n) FROM now CROSS JOIN n CROSS JOIN l LEFT JOIN near ON near.dst = now.id WHERE k < {k})
    ) SELECT id, round(rank, 9) AS rank FROM pr WHERE k = ({last})"""


_small = "SELECT coalesce(min(k), 30) FROM (SELECT a.k, max(abs(a.rank - b.rank)) AS most FROM pr a JOIN pr b ON a.id = b.id AND a.k = b.k + 1 GROUP BY a.k) WHERE most < 1e-4"
query("pagerank_redistribute", pagerank_more_sql(LINKS, 10, "sum(rank)", "10"))(lambda s, d: _pr(R.pagerank(B.page_links(s, d), 10, dangling="redistribute").select(F.col("Rank").alias("rank"))))
query("pagerank_until_small_change", pagerank_more_sql(LINKS, 30, "0.0 * count(*)", _small))(lambda s, d: _pr(R.pagerank(B.page_links(s, d), 30, eps=1e-4).select(F.col("Rank").alias("rank"))))
query("hand_pagerank", pagerank_sql(flow("a"), 10))(lambda s, d: _pr(H.pagerank(B.part_flow(s, d, "a"), 10)))
query("pagerank_part_flow_30", pagerank_sql(flow("a"), 30))(lambda s, d: _pr(R.pagerank(B.part_flow(s, d, "a"), 30).select(F.col("Rank").alias("rank"))))
query("hand_pagerank_30", pagerank_sql(flow("a"), 30))(lambda s, d: _pr(H.pagerank(B.part_flow(s, d, "a"), 30)))
query("hand_list_rank_no_halt", _ur)(lambda s, d: H.list_rank(B.user_chains(s, d), frontier=False))
query("scc_part_flow_sparse", SCC_SQL)(lambda s, d: R.scc(B.part_flow(s, d, "c")).select(F.col("Scc").alias("scc")))
query("hand_scc", SCC_SQL)(lambda s, d: H.scc(B.part_flow(s, d, "c")))
query("scc_no_early_exit", SCC_SQL)(lambda s, d: R.scc(B.part_flow(s, d, "c"), early=False).select(F.col("Scc").alias("scc")))
_scc_r = SCC_SQL.replace(flow("c"), flow("b"))
query("scc_part_flow_r", _scc_r)(lambda s, d: R.scc(B.part_flow(s, d, "b")).select(F.col("Scc").alias("scc")))
query("hand_scc_part_flow_r", _scc_r)(lambda s, d: H.scc(B.part_flow(s, d, "b")))
query("scc_page_links", SCC_SQL.replace(flow("c"), LINKS))(lambda s, d: R.scc(B.page_links(s, d)).select(F.col("Scc").alias("scc")))
query("msf_program", MSF_SQL)(lambda s, d: R.msf_program(B.supplier_mesh(s, d)))
query("msf_program_two_rounds", MSF_SQL)(lambda s, d: R.msf_program(B.supplier_mesh(s, d), peephole=False))
query("msf_supplier_mesh", MSF_SQL)(lambda s, d: R.msf(B.supplier_mesh(s, d)))
query("msf_no_peephole", MSF_SQL)(lambda s, d: R.msf(B.supplier_mesh(s, d), peephole=False))
query("hand_msf", MSF_SQL)(lambda s, d: H.msf(B.supplier_mesh(s, d)))
KNN = """x AS (SELECT vec_id AS id, list_transform(embedding, lambda z: CAST(round(CAST(z AS DOUBLE) * 1000) AS BIGINT)) AS x FROM embeddings),
pr AS (SELECT a.id AS a, b.id AS b, CAST(list_sum(list_transform(list_zip(a.x, b.x), lambda z: (z[1] - z[2]) * (z[1] - z[2]))) AS BIGINT) AS val FROM x a JOIN x b ON a.id <> b.id),
nn AS (SELECT a, b, val FROM pr QUALIFY row_number() OVER (PARTITION BY a ORDER BY val, b) <= 5), e0 AS (SELECT DISTINCT least(a, b) AS src, greatest(a, b) AS dst, val FROM nn),
e AS (SELECT src, dst, row_number() OVER (ORDER BY val, src, dst) AS val, val AS w FROM e0)"""
_knn_sql = MSF_SQL.replace(MESH, KNN).replace("SELECT e.src, e.dst, e.val FROM e", "SELECT e.src, e.dst, e.w AS val FROM e")
query("msf_vec_knn", _knn_sql)(lambda s, d: R.msf(B.vec_knn(s, d)))
query("msf_program_vec_knn", _knn_sql)(lambda s, d: R.msf_program(B.vec_knn(s, d)))
query("roots_geo_forest", f"WITH RECURSIVE {FOREST_SQL}, r(id, root, depth) AS (SELECT id, id, 0 FROM f WHERE id = p UNION ALL SELECT f.id, r.root, r.depth + 1 FROM r JOIN f ON f.p = r.id AND f.id <> f.p) SELECT id, root, depth::BIGINT AS depth FROM r")(
    lambda s, d: R.roots(B.geo_forest(s, d)).select(F.col("Root").alias("root"), F.col("Depth").alias("depth"))
)
query("preorder_geo_forest", f"WITH RECURSIVE {FOREST_SQL}, r(id, path) AS (SELECT id, [id] FROM f WHERE id = p UNION ALL SELECT f.id, list_append(r.path, f.id) FROM r JOIN f ON f.p = r.id AND f.id <> f.p), n AS (SELECT id, row_number() OVER (ORDER BY path) - 1 AS pre FROM r) SELECT id, pre FROM n")(
    lambda s, d: R.preorder(B.geo_forest(s, d))
)
query("matching_cust_part")(lambda s, d: R.bipartite_matching(B.cust_part(s, d)))
query("weight_matching_vec_knn")(lambda s, d: R.weight_matching(B.vec_knn(s, d)))


def matching_faults(g: Graph, pairs: DataFrame) -> DataFrame:
    """One row, all 0 for a maximal matching: pairs that are no edge, vertices in two pairs, and edges with two free ends."""
    a, b = pairs.columns[:2]
    m = pairs.select(F.col(a).alias("a"), F.col(b).alias("b"))
    e = g.edges.select(F.least("src", "dst").alias("x"), F.greatest("src", "dst").alias("y")).distinct()
    ends = m.select(F.col("a").alias("v")).union(m.select("b"))
    no_edge = m.select(F.least("a", "b").alias("x"), F.greatest("a", "b").alias("y")).join(e, ["x", "y"], "left_anti")
    twice = ends.groupBy("v").count().filter("count > 1")
    taken = ends.distinct()
    free = e.join(taken, F.col("x") == F.col("v"), "left_anti").join(taken, F.col("y") == F.col("v"), "left_anti")
    one = lambda df, name: df.agg(F.count(F.lit(1)).alias(name))
    return one(no_edge, "no_edge").crossJoin(one(twice, "twice")).crossJoin(one(free, "free"))  # one row each


_faultless = "SELECT 0 AS no_edge, 0 AS twice, 0 AS free"
query("matching_faults_cust_part", _faultless)(lambda s, d: (lambda g: matching_faults(g, R.bipartite_matching(g).transform(lambda m: materialise(m)[0])))(B.cust_part(s, d).stored()))
query("matching_faults_vec_knn", _faultless)(lambda s, d: (lambda g: matching_faults(g, R.weight_matching(g).transform(lambda m: materialise(m)[0])))(B.vec_knn(s, d).stored()))


@query("pattern_two_cycles", f"WITH {flow('c')} SELECT DISTINCT a.src AS id FROM e a JOIN e b ON a.src = b.dst AND a.dst = b.src")
def two_cycles(s, d):
    """Vertices with an edge to one that has an edge back."""
    return run(P.two_cycles(), R.with_mirrors(B.part_flow(s, d, "c"))).state.filter("Hit").select("id")


query("pattern_same_nation", "SELECT DISTINCT 30000000000 + o_orderkey AS id FROM orders JOIN customer ON c_custkey = o_custkey JOIN nation ON n_nationkey = c_nationkey WHERE n_regionkey = 1")(
    lambda s, d: R.pattern(B.geo_forest(s, d), lambda u: V.Region[V.Nation[V.Cust[u]]].eq(1))
)


@query("recursive_sql_hops", dist_sql("e AS (SELECT lag(event_id) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS src, event_id AS dst FROM events QUALIFY src IS NOT NULL), v AS (SELECT event_id AS id FROM events)", "1"))
def recursive_hops(s, d):
    """Hops from event 0 along its user's chain by SQL recursion. A chain is no longer than the events of the busiest user, which bounds the levels."""
    events = load(s, d, "events")
    longest = events.groupBy("user_id").count().agg(F.max("count")).first()[0] or 0
    events.select(F.col("event_id").alias("id")).createOrReplaceTempView("farfield_v")
    e = B.predecessors(events.select(F.col("event_id").alias("id"), "ts", "user_id"), "id", ["ts", "id"], "user_id").filter("Pred IS NOT NULL")
    materialise(e.select(F.col("Pred").alias("src"), F.col("id").alias("dst")))[0].createOrReplaceTempView("farfield_e")
    return H.recursive_sssp(s, "farfield_v", "farfield_e", 0, longest)


# --- measures ---


@query("read_plan_rounds", """WITH c AS (SELECT count(*) AS depth FROM orders GROUP BY o_custkey)
SELECT depth, count(*) AS chains, CASE WHEN depth < 2 THEN 0 ELSE 1 + ceil(log2(depth)) END::BIGINT AS planned, CASE WHEN depth < 2 THEN 0 ELSE 2 * (depth - 1) END::BIGINT AS request_reply FROM c GROUP BY depth""")
def read_plan_rounds(s, d):
    """Rounds that the newest order of a customer takes to read through to the customer, by the number of orders, and how many customers have so many. There are as
    many rows as different numbers; each is planned once, by a task."""
    let_workers_import(s)
    depths = load(s, d, "orders").groupBy("o_custkey").agg(F.count(F.lit(1)).alias("depth")).groupBy("depth").agg(F.count(F.lit(1)).alias("chains"))

    def planned(batches):
        for b in batches:
            chains = [[Knows((), ("Pred",) * k)] for k in b["depth"]]
            yield b.assign(planned=[plan_reads(c).rounds for c in chains], request_reply=[plan_reads(c, "request_reply").rounds for c in chains])

    return depths.mapInPandas(planned, "depth long, chains long, planned long, request_reply long")


def six(s, d) -> dict:
    """The six programs on small graphs: name -> a function of the runtime's flags that gives a Result."""
    ranked = lambda: R.with_rank(B.page_links(s, d))
    init = lambda name: step(lambda u: [local(getattr(V, name)[u], getattr(V, name)[u])])
    return {
        "sssp": lambda **f: R.sssp(B.part_flow(s, d, "b"), **f), "pagerank": lambda **f: run(init("Rank") >> P.pagerank(10), ranked(), **f), "scc": lambda **f: R.scc(B.page_links(s, d), **f),
        "components": lambda **f: R.components(B.doc_exact(s, d), **f), "list_rank": lambda **f: R.list_rank(B.turn_chain(s, d), **f), "msf": lambda **f: R.msf_run(B.supplier_mesh(s, d), **f),
    }


@query("merging_ablation")
def merging_ablation(s, d):
    """The six programs as they are and without merging and fusing: supersteps as counted while they ran, passes, jobs, exchanges and seconds."""
    rows = []
    for name, of in six(s, d).items():
        for merged in (True, False):
            x = of(merge=merged, fuse=merged).ledger
            rows.append((name, merged, x.supersteps, sum(x.iterations), x.jobs, round(x.seconds, 3)))
    return s.createDataFrame(rows, "program string, merged boolean, supersteps int, passes int, jobs int, seconds double")


@query("ledger_list_rank", """WITH c AS (SELECT conv_id, count(*) AS n FROM conversations GROUP BY conv_id), k AS (SELECT CAST(ceil(log2(max(n))) AS BIGINT) + 1 AS k FROM c)
SELECT k AS passes, 2 + 2 * k + 1 - 1 AS merged, 3 + 4 * k AS general FROM k""")
def ledger_list_rank(s, d):
    """Passes and supersteps of list ranking as they were counted in two runs; a pass has three states, of which merging shares one and takes the test away."""
    on, off = (R.list_rank(B.turn_chain(s, d), merge=x, fuse=x).ledger for x in (True, False))
    return s.createDataFrame([(on.iterations[0], on.supersteps, off.supersteps)], "passes long, merged long, general long")


@query("redundant_messages")
def redundant_messages(s, d):
    """Messages of the shared sending states that nobody reads, and all messages, by kind, of the six programs."""
    rows = []
    for name, of in six(s, d).items():
        x = of(measure=True).ledger
        rows.append((name, x.redundant, sum(n for _, n, _ in x.messages), sum(n for _, _, n in x.messages), x.exchanges))
    return s.createDataFrame(rows, "program string, redundant long, sent long, received_if_combined long, exchanges long")


@query("message_counts_part_flow", f"WITH {flow('b')} SELECT count(*) AS sent, count(DISTINCT dst) AS receivers FROM e")
def message_counts(s, d):
    from farfield.metrics import message_counts as counts

    return counts(B.part_flow(s, d, "b").edges, "dst")


@query("iterations_user_chain", """WITH p AS (SELECT user_id, event_id, row_number() OVER (PARTITION BY user_id ORDER BY ts, event_id) AS pos FROM events),
f AS (SELECT user_id, arg_min(pos, event_id) AS first_pos FROM p GROUP BY user_id) SELECT 'hashmin' AS program, max(abs(pos - first_pos)) + 1 AS passes FROM p JOIN f USING (user_id)""")
def iterations(s, d):
    """Passes of flooding on long chains: as many as the least id of a chain has to walk, and one that changes nothing."""
    return s.createDataFrame([("hashmin", R.hashmin(B.user_chain_graph(s, d)).ledger.iterations[0])], "program string, passes long")


@query("iterations_by_diameter")
def iterations_by_diameter(s, d):
    """Pointer jumping and flooding on long chains, and jumping on the one chain of all events, which flooding would take as many passes for as there are events. On user chains
    all passes run inside blocks of users, so jobs do not grow with passes there."""
    users, events = B.user_chain_graph(s, d), B.event_chain_graph(s, d)
    runs = (("components", "user chains", R.components(users, blocks=True).ledger), ("hashmin", "user chains", R.hashmin(users, blocks=True).ledger), ("components", "event chain", R.components(events).ledger))
    rows = [(n, g, x.iterations[-1], x.jobs, x.supersteps) for n, g, x in runs]
    return s.createDataFrame(rows, "program string, graph string, passes int, jobs int, supersteps int")


@query("partition_sweep")
def partition_sweep(s, d):
    """Seconds of two programs by the number of shuffle partitions, mean of three; experiments.py sweeps threads."""
    from farfield.metrics import time3

    before, rows = s.conf.get("spark.sql.shuffle.partitions"), []
    try:
        for n in (4, 8, 16):
            s.conf.set("spark.sql.shuffle.partitions", n)
            for name in ("components", "list_rank"):
                rows.append((name, n, round(time3(lambda name=name: six(s, d)[name]()), 3)))
    finally:
        s.conf.set("spark.sql.shuffle.partitions", before)
    return s.createDataFrame(rows, "program string, partitions int, seconds double")


@query("plan_operators")
def plan_operators(s, d):
    """Operators in the plan of one pass of the programs, before adaptive changes."""
    from farfield.metrics import plan_stats

    rows = []
    for name, p, g in (("components", P.components(), B.doc_exact(s, d)), ("hashmin", P.hashmin(), B.doc_exact(s, d)), ("list_rank", P.list_rank(), B.turn_chain(s, d))):
        body = p.parts[1].body
        flat = P.chain(("id",), "D") >> body if name != "list_rank" else p.parts[0] >> body
        rows += [(name, k, n) for k, n in plan_stats(run(flat, g.stored()).state).items()]
    return s.createDataFrame(rows, "program string, operator string, n int")


# --- sources, graphs ---

query("scan_nation", "SELECT n_nationkey, n_name FROM nation WHERE n_regionkey = 1")(lambda s, d: load(s, d, "nation").filter("n_regionkey = 1").select("n_nationkey", "n_name"))
query("graph_validate_part_flow", f"WITH {flow('b')} SELECT 0 AS repeated_ids, count(CASE WHEN v.id IS NULL THEN 1 END) AS dangling_ends, 0 AS self_loops, 0 AS repeated_edges, 0 AS unmirrored_edges FROM (SELECT src AS x FROM e UNION ALL SELECT dst FROM e) LEFT JOIN v ON v.id = x")(lambda s, d: B.part_flow(s, d, "b").validate())
query("intern_ids_pages", "SELECT count(DISTINCT url) AS keys, count(DISTINCT url) AS ids FROM pages")(lambda s, d: intern_ids(load(s, d, "pages"), "url").agg(F.countDistinct("url").alias("keys"), F.countDistinct("id").alias("ids")))
query("adjacency_supplier_mesh", f"WITH {MESH}, b AS (SELECT src, dst, val FROM e UNION ALL SELECT dst, src, val FROM e) SELECT s_suppkey AS id, count(b.dst) AS n, min(b.dst) AS first FROM supplier LEFT JOIN b ON b.src = s_suppkey GROUP BY 1")(
    lambda s, d: B.supplier_mesh(s, d).with_adjacency(100).groupBy("id").agg(F.sum(F.coalesce(F.size("adjacent"), F.lit(0))).cast("long").alias("n"), F.min(F.array_min(F.transform("adjacent", lambda x: x["ref"]))).alias("first"))
)
query("induced_part_flow", f"WITH {flow('b')} SELECT src, dst, val FROM e WHERE src % 2 = 0 AND dst % 2 = 0")(lambda s, d: (lambda g: g.induced(g.vertices.filter("id % 2 = 0")).edges)(B.part_flow(s, d, "b")))
query("edges_page_links", f"WITH {LINKS} SELECT src, dst FROM e")(lambda s, d: B.page_links(s, d).edges.select("src", "dst"))
query("edges_cust_part", "SELECT DISTINCT o_custkey AS src, -(l_partkey + 1) AS dst FROM lineitem JOIN orders ON l_orderkey = o_orderkey WHERE l_returnflag = 'R' AND l_discount >= 0.095")(lambda s, d: B.cust_part(s, d).edges.filter("src >= 0").select("src", "dst"))
query("degrees_part_flow", f"WITH {flow('b')} SELECT id, (SELECT count(*) FROM e WHERE dst = id) AS ins, (SELECT count(*) FROM e WHERE src = id) AS outs FROM v")(lambda s, d: O.degrees(B.part_flow(s, d, "b")))
query("degree_histogram", f"WITH {flow('b')}, g AS (SELECT v.id, count(e.src) AS degree FROM v LEFT JOIN e ON e.src = v.id GROUP BY v.id) SELECT degree, count(*) AS n FROM g GROUP BY degree")(lambda s, d: O.degrees(B.part_flow(s, d, "b")).groupBy(F.col("outs").alias("degree")).agg(F.count(F.lit(1)).alias("n")))
query("component_size_histogram", f"WITH c AS ({_exact}), z AS (SELECT comp, count(*) AS size FROM c GROUP BY comp) SELECT size, count(*) AS n FROM z GROUP BY size")(lambda s, d: O.component_sizes(QUERIES["components_doc_exact"](s, d), "comp"))
query("modularity_supplier_mesh", f"WITH {MESH}, b AS (SELECT src, dst FROM e UNION ALL SELECT dst, src FROM e), l AS (SELECT src % 4 AS a, dst % 4 AS z FROM b), y AS (SELECT a, sum((a = z)::INT) AS i, count(*) AS g FROM l GROUP BY a) SELECT round(sum(i) / sum(g) - sum(g::DOUBLE * g) / (sum(g)::DOUBLE * sum(g)), 9) AS modularity FROM y")(
    lambda s, d: (lambda g: O.modularity(g, g.vertices.withColumn("l", F.col("id") % 4), "l").select(F.round("modularity", 9).alias("modularity")))(B.supplier_mesh(s, d))
)
query("triangles_part_flow", f"WITH {flow('c')}, {BOTH} SELECT x.src AS id, count(*) // 2 AS triangles FROM b x JOIN b y ON x.dst = y.src JOIN b z ON y.dst = z.src AND z.dst = x.src GROUP BY x.src")(lambda s, d: O.triangles(B.undirected(B.part_flow(s, d, "c"))))
query("top_edges_supplier_mesh", f"WITH {MESH}, b AS (SELECT src, dst, val FROM e UNION ALL SELECT dst, src, val FROM e) SELECT src, dst, val, CAST(row_number() OVER (PARTITION BY src ORDER BY val, dst) AS INTEGER) AS r FROM b QUALIFY r <= 3")(lambda s, d: O.top_edges(B.supplier_mesh(s, d), 3))


@query("pointer_join_hot", f"WITH {FOREST_SQL} SELECT f.id, g.p AS far FROM f JOIN f g ON f.p = g.id")
def pointer_join_hot(s, d):
    v = B.geo_forest(s, d).vertices.select("id", "Parent")
    return O.pointer_join(v, "Parent", ["Parent"], O.hot_targets(v, "Parent", 0.01)).select("id", F.col("far_Parent").alias("far"))


# --- joins, aggregates, windows, sets and functions on the tables ---


def simple(name: str, sql: str, spark_sql: str | None = None, tables: tuple[str, ...] = ()):
    """A query that both engines read alike, over views."""

    def fn(s, d):
        for t in tables:
            load(s, d, t).createOrReplaceTempView(t)
        return s.sql(spark_sql or sql)

    query(name, sql)(fn)


simple("join_inner", "SELECT o_orderkey, c_name FROM orders JOIN customer ON o_custkey = c_custkey", tables=("orders", "customer"))
simple("join_left", "SELECT p_partkey, l_linenumber FROM part LEFT JOIN lineitem ON p_partkey = l_partkey AND l_quantity > 49", tables=("part", "lineitem"))
simple("join_full", "SELECT c_custkey, s_suppkey FROM customer FULL OUTER JOIN supplier ON c_custkey = s_suppkey * 20", tables=("customer", "supplier"))
simple("join_semi", "SELECT c_custkey FROM customer WHERE EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey AND o_totalprice > 300000)", tables=("customer", "orders"))
simple("join_anti", "SELECT c_custkey FROM customer WHERE NOT EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey)", tables=("customer", "orders"))
simple("join_theta", "SELECT a.r_regionkey AS x, b.r_regionkey AS y FROM region a JOIN region b ON a.r_regionkey < b.r_regionkey", tables=("region",))
simple("join_lateral", "SELECT n_nationkey, s_suppkey FROM nation, LATERAL (SELECT s_suppkey FROM supplier WHERE s_nationkey = n_nationkey ORDER BY s_suppkey LIMIT 2) t", tables=("nation", "supplier"))
query("join_broadcast", "SELECT s_suppkey, n_name FROM supplier JOIN nation ON s_nationkey = n_nationkey")(lambda s, d: load(s, d, "supplier").join(F.broadcast(load(s, d, "nation")), F.col("s_nationkey") == F.col("n_nationkey")).select("s_suppkey", "n_name"))


@query("join_range_events", "SELECT a.event_id AS a, b.event_id AS b FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_id <> b.event_id AND epoch_us(b.ts) BETWEEN epoch_us(a.ts) AND epoch_us(a.ts) + 3600000000")
def join_range(s, d):
    e = load(s, d, "events").select("event_id", "user_id", F.unix_micros(F.col("ts").cast("timestamp")).alias("t"))
    pairs = O.range_join(e.select(F.col("event_id").alias("a"), "user_id", F.col("t").alias("ta")), e.select(F.col("event_id").alias("b"), "user_id", F.col("t").alias("tb")), "ta", "tb", 3_600_000_000, ["user_id"])
    return pairs.filter("a <> b").select("a", "b")


@query("join_as_of", "SELECT event_id, (SELECT arg_max(p.event_id, (p.ts, p.event_id)) FROM events p WHERE p.user_id = e.user_id AND p.ts <= e.ts AND p.event_type = 'purchase') AS last FROM events e WHERE event_type = 'click'")
def join_as_of(s, d):
    e = load(s, d, "events")
    left = e.filter("event_type = 'click'").select("event_id", "user_id", "ts")
    return O.as_of_join(left, e.filter("event_type = 'purchase'").select("user_id", "ts", F.col("event_id").alias("p")), "user_id", "ts", "p", "last").select("event_id", "last")


simple("agg_having", "SELECT l_partkey, count(*) AS n, CAST(sum(round(l_quantity)) AS BIGINT) AS q FROM lineitem GROUP BY l_partkey HAVING count(*) > 35", tables=("lineitem",))
simple("agg_cube", "SELECT lang, source, count(*) AS n FROM documents GROUP BY CUBE (lang, source)", tables=("documents",))
simple("agg_rollup", "SELECT lang, source, count(*) AS n FROM documents GROUP BY ROLLUP (lang, source)", tables=("documents",))
simple("agg_grouping_sets", "SELECT lang, source, count(*) AS n FROM documents GROUP BY GROUPING SETS ((lang), (source), ())", tables=("documents",))
simple("agg_distinct", "SELECT event_type, count(DISTINCT user_id) AS users FROM events GROUP BY event_type", tables=("events",))
simple("agg_boolean_bits", "SELECT l_returnflag, bool_or(l_quantity > 49) AS some, bool_and(l_quantity > 0) AS every, bit_or(l_linenumber) AS bits, bit_and(l_linenumber) AS common FROM lineitem GROUP BY l_returnflag", tables=("lineitem",))
simple("agg_extremes_by", "SELECT o_custkey, min_by(o_orderkey, o_totalprice) AS least, max_by(o_orderkey, o_totalprice) AS most FROM orders GROUP BY o_custkey", tables=("orders",))
query("agg_pivot", "SELECT l_returnflag, count(CASE WHEN l_linestatus = 'F' THEN 1 END) AS f, count(CASE WHEN l_linestatus = 'O' THEN 1 END) AS o FROM lineitem GROUP BY l_returnflag")(
    lambda s, d: load(s, d, "lineitem").groupBy("l_returnflag").pivot("l_linestatus", ["F", "O"]).count().select("l_returnflag", F.coalesce("F", F.lit(0)).alias("f"), F.coalesce("O", F.lit(0)).alias("o"))
)
query("agg_salted_sum", "SELECT l_suppkey, CAST(sum(CAST(round(l_extendedprice * 100) AS BIGINT)) AS BIGINT) AS total FROM lineitem GROUP BY l_suppkey")(lambda s, d: O.salted_sum(load(s, d, "lineitem"), "l_suppkey", B.cents("l_extendedprice")))
simple("window_ranks", "SELECT s_suppkey, rank() OVER (PARTITION BY s_nationkey ORDER BY s_suppkey // 10) AS r, dense_rank() OVER (PARTITION BY s_nationkey ORDER BY s_suppkey // 10) AS dr, ntile(3) OVER (PARTITION BY s_nationkey ORDER BY s_suppkey) AS t FROM supplier", "SELECT s_suppkey, CAST(rank() OVER (PARTITION BY s_nationkey ORDER BY s_suppkey DIV 10) AS BIGINT) AS r, CAST(dense_rank() OVER (PARTITION BY s_nationkey ORDER BY s_suppkey DIV 10) AS BIGINT) AS dr, CAST(ntile(3) OVER (PARTITION BY s_nationkey ORDER BY s_suppkey) AS BIGINT) AS t FROM supplier", ("supplier",))
simple("window_lag_lead", "SELECT event_id, lag(event_id) OVER w AS before, lead(event_id, 2) OVER w AS after FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)", tables=("events",))
simple("window_values", "SELECT event_id, first_value(event_id) OVER w AS f, last_value(event_id) OVER w AS l, nth_value(event_id, 2) OVER w AS n FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING)", tables=("events",))
simple("window_running_sum", "SELECT event_id, CAST(sum(CAST(round(value * 100) AS BIGINT)) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS UNBOUNDED PRECEDING) AS BIGINT) AS total FROM events", tables=("events",))
simple("window_range", "SELECT o_orderkey, count(*) OVER (PARTITION BY o_custkey ORDER BY CAST(date_part('epoch', o_orderdate) AS BIGINT) // 86400 RANGE BETWEEN 90 PRECEDING AND CURRENT ROW) AS n FROM orders", "SELECT o_orderkey, count(*) OVER (PARTITION BY o_custkey ORDER BY datediff(o_orderdate, DATE'1970-01-01') RANGE BETWEEN 90 PRECEDING AND CURRENT ROW) AS n FROM orders", ("orders",))
simple("window_distribution", "SELECT s_suppkey, round(percent_rank() OVER (PARTITION BY s_nationkey ORDER BY s_suppkey), 9) AS p, round(cume_dist() OVER (PARTITION BY s_nationkey ORDER BY s_suppkey), 9) AS c FROM supplier", tables=("supplier",))
simple("top_k", "SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 20", tables=("orders",))
simple("top_k_offset", "SELECT o_orderkey FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 10 OFFSET 5", tables=("orders",))
query("top_k_per_group", "SELECT o_custkey, o_orderkey FROM orders QUALIFY row_number() OVER (PARTITION BY o_custkey ORDER BY o_totalprice DESC, o_orderkey) <= 2")(
    lambda s, d: load(s, d, "orders").withColumn("r", F.row_number().over(Window.partitionBy("o_custkey").orderBy(F.desc("o_totalprice"), "o_orderkey"))).filter("r <= 2").select("o_custkey", "o_orderkey")
)
simple("set_union", "SELECT c_nationkey AS k FROM customer UNION SELECT s_nationkey FROM supplier", tables=("customer", "supplier"))
simple("set_intersect", "SELECT c_custkey AS k FROM customer INTERSECT SELECT s_suppkey FROM supplier", tables=("customer", "supplier"))
simple("set_except", "SELECT c_custkey AS k FROM customer EXCEPT SELECT o_custkey FROM orders", tables=("customer", "orders"))
simple("functions_string", "SELECT doc_id, md5(text) AS m, length(trim(text)) AS n, substring(text, 1, 10) AS s, lower(lang) || '-' || upper(source) AS c FROM documents", "SELECT doc_id, md5(text) AS m, CAST(length(trim(text)) AS BIGINT) AS n, substring(text, 1, 10) AS s, concat(lower(lang), '-', upper(source)) AS c FROM documents", ("documents",))
simple("functions_date", "SELECT o_orderkey, date_trunc('month', o_orderdate)::TIMESTAMP AS m, date_part('year', o_orderdate) AS y, date_diff('day', TIMESTAMP '1992-01-01', o_orderdate) AS n FROM orders", "SELECT o_orderkey, CAST(date_trunc('month', o_orderdate) AS TIMESTAMP_NTZ) AS m, CAST(year(o_orderdate) AS BIGINT) AS y, CAST(datediff(o_orderdate, DATE'1992-01-01') AS BIGINT) AS n FROM orders", ("orders",))
simple("functions_math", "SELECT p_partkey, abs(p_size - 25) AS a, sqrt(p_size) AS s, p_size % 7 AS m, greatest(p_size, 10) AS g, least(p_size, 10) AS l, round(p_retailprice, 1) AS r FROM part", tables=("part",))
simple("functions_array", "SELECT vec_id, CAST(list_sum(list_transform(embedding, lambda x: CAST(round(CAST(x AS DOUBLE) * 1000) AS BIGINT))) AS BIGINT) AS total, len(list_filter(embedding, lambda x: x > 0)) AS positive FROM embeddings", "SELECT vec_id, aggregate(transform(embedding, x -> CAST(round(CAST(x AS DOUBLE) * 1000) AS BIGINT)), CAST(0 AS BIGINT), (a, x) -> a + x) AS total, CAST(size(filter(embedding, x -> x > 0)) AS BIGINT) AS positive FROM embeddings", ("embeddings",))
query("functions_map", "SELECT conv_id, count(*) AS n, max(CASE WHEN turn = 0 THEN role END) AS first FROM conversations GROUP BY conv_id")(
    lambda s, d: load(s, d, "conversations").groupBy("conv_id").agg(F.map_from_entries(F.collect_list(F.struct("turn", "role"))).alias("m")).select("conv_id", F.size(F.map_keys("m")).cast("long").alias("n"), F.try_element_at("m", F.lit(0).cast("long")).alias("first"))
)
simple("functions_json", "SELECT event_id, json_extract_string(props, '$.k') AS k, length(props) AS n FROM events", "SELECT event_id, get_json_object(props, '$.k') AS k, CAST(length(props) AS BIGINT) AS n FROM events", ("events",))

# --- user-defined functions ---


@query("udf_pandas_scalar", "SELECT s_suppkey, s_suppkey * 2 + 1 AS x FROM supplier")
def udf_scalar(s, d):
    @F.pandas_udf("long")
    def twice(x: pd.Series) -> pd.Series:
        return x * 2 + 1

    return load(s, d, "supplier").select("s_suppkey", twice("s_suppkey").alias("x"))


@query("udaf_grouped", "SELECT s_nationkey, CAST(max(s_suppkey) - min(s_suppkey) AS BIGINT) AS spread FROM supplier GROUP BY s_nationkey")
def udaf_grouped(s, d):
    @F.pandas_udf("long")
    def spread(x: pd.Series) -> int:
        return int(x.max() - x.min())

    return load(s, d, "supplier").groupBy("s_nationkey").agg(spread("s_suppkey").alias("spread"))


@query("udtf_links", """SELECT page_id, count(*) AS links FROM (SELECT page_id, unnest(regexp_extract_all(html, 'href="([^"]*)"', 1)) AS h FROM pages) GROUP BY page_id""")
def udtf_links(s, d):
    @F.udtf(returnType="h string")
    class Links:
        def eval(self, html: str):
            import re

            for h in re.findall(r'href="([^"]*)"', html or ""):
                yield (h,)

    s.udtf.register("farfield_links", Links)
    load(s, d, "pages").createOrReplaceTempView("pages")
    return s.sql("SELECT page_id, count(*) AS links FROM pages, LATERAL farfield_links(html) GROUP BY page_id")


SMALL = 1000


@query("finisher_small_components", _exact)
def finisher(s, d):
    """Components of at most SMALL vertices are solved in one task each, after a cheap key has brought them together; larger ones by sums, which
    Spark reduces before it shuffles."""
    def solve(rows: pd.DataFrame) -> pd.DataFrame:
        return pd.DataFrame({"id": rows["id"], "comp": rows["id"].min()})

    docs = load(s, d, "documents").select(F.col("doc_id").alias("id"), F.md5("text").alias("k"))
    sizes = docs.groupBy(F.col("k").alias("key")).agg(F.count(F.lit(1)).alias("n"), F.min("id").alias("comp"))
    known = docs.join(sizes, F.col("k") == F.col("key"))
    return known.filter(F.col("n") <= SMALL).select("id", "k").groupBy("k").applyInPandas(solve, "id long, comp long").union(known.filter(F.col("n") > SMALL).select("id", "comp"))


# --- streams over stored tables, run to their end ---


def _streamed(s, d, make, mode="append", parts=4):
    """Replays events in order and reads what the stream wrote."""
    from farfield.plans.store import shared_folder

    e = load(s, d, "events")
    src = S.replay(s, e, parts, "ts")
    out = f"{src}-out"
    q = S.start(make(S.source(s, src)), mode, f"{src}-checkpoint", out)
    q.awaitTermination()
    assert shared_folder(s)
    return s.read.parquet(out)


query("stream_running_rank", f"WITH {EVENTS} SELECT id AS event_id, CAST(sum(v) OVER (PARTITION BY user_id ORDER BY ts, id ROWS UNBOUNDED PRECEDING) AS BIGINT) AS rank FROM ev")(lambda s, d: _streamed(s, d, S.running_rank))
_start = lambda df, w: df.select(F.col(f"{w}.start").cast("timestamp_ntz").alias("start"), "user_id", "n")
#: A window is out when the watermark, an hour behind the newest event, has passed its end.
_OUT = "(SELECT max(ts) - INTERVAL 1 HOUR FROM events)"
_HALVES = "SELECT user_id, time_bucket(INTERVAL 30 MINUTE, ts, TIMESTAMP '2000-01-01') AS h FROM events"
query("stream_tumbling", f"SELECT time_bucket(INTERVAL 1 HOUR, ts, TIMESTAMP '2000-01-01') AS start, user_id, count(*) AS n FROM events GROUP BY 1, 2 HAVING start + INTERVAL 1 HOUR <= {_OUT}")(lambda s, d: _start(_streamed(s, d, lambda x: S.windowed_pairs(x)), "window"))
query("stream_sliding", f"SELECT start, user_id, count(*) AS n FROM (SELECT user_id, h AS start FROM ({_HALVES}) UNION ALL SELECT user_id, h - INTERVAL 30 MINUTE FROM ({_HALVES})) GROUP BY 1, 2 HAVING start + INTERVAL 1 HOUR <= {_OUT}")(lambda s, d: _start(_streamed(s, d, lambda x: S.windowed_pairs(x, slide="30 minutes")), "window"))
query("stream_sessions", f"WITH f AS (SELECT user_id, ts, event_id, coalesce(ts > lag(ts) OVER w + INTERVAL 30 MINUTE, true) AS first FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)), g AS (SELECT *, sum(first::INT) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS UNBOUNDED PRECEDING) AS s FROM f) SELECT min(ts) AS start, user_id, count(*) AS n FROM g GROUP BY user_id, s HAVING max(ts) + INTERVAL 30 MINUTE <= {_OUT}")(lambda s, d: _start(_streamed(s, d, S.sessions), "session_window"))
query("stream_interval_join", "SELECT a.event_id AS src, b.event_id AS dst FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 1 HOUR WHERE a.event_type = 'click' AND b.event_type = 'purchase'")(lambda s, d: _streamed(s, d, lambda x: S.interval_edges(x.filter("event_type = 'click'"), x.filter("event_type = 'purchase'"))))
query("stream_dedup", "SELECT DISTINCT user_id % 50 AS src, length(event_type) AS dst FROM events")(lambda s, d: _streamed(s, d, lambda x: S.dedup_edges(x.select((F.col("user_id") % 50).alias("src"), F.length("event_type").cast("long").alias("dst"), "ts"), "10000 days")).select("src", "dst"))


@query("stream_components", _users)
def stream_components(s, d):
    """Chains of users arrive edge by edge; the labels after the last batch."""
    e = load(s, d, "events").select(F.col("event_id").alias("id"), "ts", "user_id")
    edges = B.predecessors(e, "id", ["ts", "id"], "user_id").select(F.coalesce("Pred", "id").alias("src"), F.col("id").alias("dst"), "ts")
    src = S.replay(s, edges, 3, "ts")
    keep = S.Components(s)
    q = S.start(S.source(s, src), "append", f"{src}-checkpoint", batch=keep)
    q.awaitTermination()
    return keep.labels


ENTRY = QUERIES["components_user_chain"]
