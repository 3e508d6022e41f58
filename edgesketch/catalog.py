"""The engine's queries by name, each with the SQL that checks it where SQL can express it.

A sketch's answer is compared with exact SQL over the raw tables; the SQL never sees the sketch.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from edgesketch.functions.sampler import SketchParams
from edgesketch.operators import buckets, certificate, cuts, exact
from edgesketch.operators.batching import BatchPolicy
from edgesketch.operators.cache import ForestCache
from edgesketch.operators.forest import spanning_forest
from edgesketch.operators.reach import hashed_pairs, hashed_pairs_sql, reachable
from edgesketch.operators.sketch import GraphSketch
from edgesketch.plans import accuracy, costs, workloads
from edgesketch.plans.workloads import ends_of, prepared, user_key_stream
from edgesketch.sources import generate, graphs
from edgesketch.sources import updates as U
from edgesketch.streaming import ingest
from edgesketch.tables import materialize, scratch_path, table

Q: dict = {}
SQL: dict[str, str] = {}


def query(name: str, sql: str | None = None):
    def add(f):
        Q[name] = f
        if sql is not None:
            SQL[name] = sql
        return f

    return add


# ---------------------------------------------------------------- components


def components_sql(edges: str, vertices: str | None = None) -> str:
    return f"""
WITH RECURSIVE e AS MATERIALIZED ({edges}), b AS MATERIALIZED (SELECT u, v FROM e UNION SELECT v, u FROM e),
verts AS ({vertices or "SELECT u AS x FROM b"}),
cc(vertex, component) USING KEY (vertex) AS (
  SELECT DISTINCT x, x FROM verts
  UNION SELECT b.v, min(c.component) FROM cc c JOIN b ON b.u = c.vertex JOIN recurring.cc r ON r.vertex = b.v WHERE c.component < r.component GROUP BY b.v)
SELECT vertex::BIGINT AS vertex, component::BIGINT AS component FROM cc"""


ALL_ROWS = {"docs_exact": ("documents", "doc_id"), "docs_lines": ("documents", "doc_id"), "emb_label": ("embeddings", "vec_id"), "emb_cos": ("embeddings", "vec_id")}


def sketched(spark: SparkSession, sf_dir: str, name: str, policy: BatchPolicy = BatchPolicy(), stars: bool = False, **params) -> tuple[GraphSketch, DataFrame]:
    e, v, n = prepared(spark, sf_dir, name, stars)
    vertices = materialize(ends_of(e), "vertices")  # each forest of a certificate starts from them
    if name in ALL_ROWS:
        where, key = ALL_ROWS[name]
        vertices = table(spark, sf_dir, where).select(F.col(key).alias("vertex")).distinct()
        v = max(v, vertices.agg(F.max("vertex")).first()[0] + 1)
    return GraphSketch.build(U.from_edges(e), SketchParams.for_edges(v, n, **params), policy), vertices


def answered(result) -> DataFrame:
    if not result.complete:
        raise RuntimeError(f"unresolved components: {result.unresolved[:10]}")
    return result.labels


def flagship(spark: SparkSession, sf_dir: str) -> DataFrame:
    s, vertices = sketched(spark, sf_dir, "part_supplier")
    return answered(spanning_forest(s, vertices=vertices))


def _components(name: str, how: dict | None = None, policy: BatchPolicy = BatchPolicy(), **params):
    def run(spark, sf_dir):
        # components of groups that are linked in all pairs are those of a star for each group
        s, vertices = sketched(spark, sf_dir, name, policy, name in graphs.CLIQUES, **params)
        return answered(spanning_forest(s, vertices=vertices, **(how or {})))

    return run


def _sql_of(name: str) -> str:
    vertices = "SELECT {1} AS x FROM {0}".format(*ALL_ROWS[name]) if name in ALL_ROWS else None
    return components_sql(graphs.oracle(name), vertices)


for _name in [*graphs.EDGES, "emb_cos"]:
    query(f"cc_{_name}", _sql_of(_name))(_components(_name))
for _key, _params in {"variant_nested": {"variant": "nested"}, "variant_columns1": {"columns": 1}, "variant_columns3": {"columns": 3}}.items():
    query(f"cc_{_key}", _sql_of("page_links"))(_components("page_links", **_params))
for _mode in ("raw", "delta", "hybrid", "tree"):
    query(f"cc_policy_{_mode}", _sql_of("page_links"))(_components("page_links", policy=BatchPolicy(_mode)))
query("cc_distributed_contraction", _sql_of("page_links"))(_components("page_links", how={"driver_limit": 0}))


def _stream_components(make, spark, sf_dir):
    stream, v, n = make(spark, sf_dir)
    s = GraphSketch.build(stream, SketchParams.for_edges(v, n))
    return answered(spanning_forest(s, vertices=ends_of(stream)))


def _bounds(stream: DataFrame) -> tuple[DataFrame, int, int]:
    stream = materialize(stream, "stream")
    r = stream.agg(F.max("v").alias("v"), F.countDistinct("u", "v").alias("n")).first()
    return stream, int(r.v) + 1, int(r.n)


def _lineitem(spark, sf_dir, extra: str) -> DataFrame:
    text = graphs.EDGES["part_supplier"].replace("SELECT l_partkey AS u", f"SELECT {extra}, l_partkey AS u")
    graphs.views(spark, sf_dir, text)
    return spark.sql(text).withColumns({"u": F.col("u").cast("long"), "v": F.col("v").cast("long")})


def toggle_part_supplier(spark, sf_dir):
    rows = _lineitem(spark, sf_dir, "unix_micros(cast(l_shipdate as timestamp)) AS seq, l_orderkey, l_linenumber")
    return _bounds(U.toggle(rows, "seq", "l_orderkey", "l_linenumber"))


def _odd(name: str, spark_or_duck=graphs.DUCKDB) -> str:
    return f"SELECT u, v FROM ({graphs.EDGES[name].format(**spark_or_duck)}) GROUP BY u, v HAVING count(*) % 2 = 1"


def _ends_sql(name: str) -> str:
    return f"SELECT u AS x FROM ({graphs.EDGES[name].format(**graphs.DUCKDB)}) UNION SELECT v FROM ({graphs.EDGES[name].format(**graphs.DUCKDB)})"


@query("cc_toggle_part_supplier", components_sql(_odd("part_supplier"), _ends_sql("part_supplier")))
def _(spark, sf_dir):
    return _stream_components(toggle_part_supplier, spark, sf_dir)


@query("cc_toggle_user_key", components_sql(_odd("user_key"), _ends_sql("user_key")))
def _(spark, sf_dir):
    stream, vertices, v, n = user_key_stream(spark, sf_dir)
    return answered(spanning_forest(GraphSketch.build(stream, SketchParams.for_edges(v, n)), vertices=vertices))


@query("cc_churn_page_links", components_sql(graphs.oracle("page_links")))
def _(spark, sf_dir):
    return _stream_components(lambda s, d: _bounds(U.churn(graphs.edges(s, d, "page_links"))), spark, sf_dir)


@query("cc_returns", components_sql("SELECT DISTINCT l_partkey AS u, (SELECT count(*) FROM part) + l_suppkey AS v FROM lineitem WHERE l_returnflag <> 'R'", _ends_sql("part_supplier")))
def _(spark, sf_dir):
    rows = _lineitem(spark, sf_dir, "datediff(l_shipdate, date'1970-01-01') AS day, l_returnflag = 'R' AS back")
    return _stream_components(lambda s, d: _bounds(U.returns(rows)), spark, sf_dir)


# ---------------------------------------------------------------- forests, reachability, cache


def _forest_sql(name: str) -> str:
    c = components_sql(graphs.oracle(name))
    return f"SELECT (count(*) - count(DISTINCT component))::BIGINT AS forest_edges, count(*)::BIGINT AS vertices, count(DISTINCT component)::BIGINT AS components, 0::BIGINT AS outside, true AS spans FROM ({c})"


def _forest_summary(name: str):
    def run(spark, sf_dir):
        s, vertices = sketched(spark, sf_dir, name)
        r = spanning_forest(s, vertices=vertices)
        c = accuracy.check_forest(r, graphs.edges(spark, sf_dir, name))
        n = r.labels.agg(F.count(F.lit(1)).alias("vertices"), F.countDistinct("component").alias("components"))
        return n.select(F.lit(c["edges"]).cast("long").alias("forest_edges"), "vertices", "components", F.lit(c["outside"]).cast("long").alias("outside"), F.lit(c["spans"] and c["distinct"]).alias("spans"))

    return run


for _name in ("part_supplier", "page_links", "order_part", "region_tree"):
    query(f"forest_summary_{_name}", _forest_sql(_name))(_forest_summary(_name))

N_PAIRS = 500


def _told(answers: DataFrame) -> DataFrame:
    """1 or 0, and -1 where an end is no vertex."""
    return answers.withColumn("connected", F.coalesce(F.col("connected").cast("int"), F.lit(-1)))


def _pairs_sql(edges: str, vertices: str | None, v: str) -> str:
    return f"""SELECT p.pair_id::BIGINT AS pair_id, p.u::BIGINT AS u, p.v::BIGINT AS v, coalesce((a.component = b.component)::INTEGER, -1) AS connected
FROM ({hashed_pairs_sql(N_PAIRS, v)}) p LEFT JOIN ({components_sql(edges, vertices)}) a ON a.vertex = p.u LEFT JOIN ({components_sql(edges, vertices)}) b ON b.vertex = p.v"""


@query("reach_pairs_order_part", _pairs_sql(graphs.oracle("order_part"), None, f"SELECT max(v) + 1 FROM ({graphs.oracle('order_part')})"))
def _(spark, sf_dir):
    s, vertices = sketched(spark, sf_dir, "order_part")
    return _told(reachable(hashed_pairs(spark, N_PAIRS, s.params.v_count), answered(spanning_forest(s, vertices=vertices))))


@query("reach_pairs_page_links", _pairs_sql(graphs.oracle("page_links"), None, f"SELECT max(v) + 1 FROM ({graphs.oracle('page_links')})"))
def _(spark, sf_dir):
    s, vertices = sketched(spark, sf_dir, "page_links")
    return _told(reachable(hashed_pairs(spark, N_PAIRS, s.params.v_count), answered(spanning_forest(s, vertices=vertices))))


def _prefix(where: str) -> str:
    text = graphs.EDGES["user_key"].format(**graphs.DUCKDB)
    return f"SELECT u, v FROM ({text} WHERE {where}) GROUP BY u, v HAVING count(*) % 2 = 1"


_LAST = "(SELECT max(event_id) FROM events)"


def _cached(spark, sf_dir):
    """(stream, cache after half of the stream, sketch builder) of user-key edges."""
    stream, vertices, v, n = user_key_stream(spark, sf_dir)
    last = table(spark, sf_dir, "events").agg(F.max("event_id")).first()[0]
    p = SketchParams.for_edges(v, n)
    build = lambda upto: lambda: GraphSketch.build(stream.where(F.col("seq") <= upto), p, epoch=upto)
    cache = ForestCache(vertices)
    half = last // 2
    cache.query(build(half), None, half)
    return stream, vertices, v, last, half, cache, build


@query("cached_components", components_sql(_prefix("true"), _ends_sql("user_key")))
def _(spark, sf_dir):
    stream, _, _, last, half, cache, build = _cached(spark, sf_dir)
    return answered(cache.query(build(last), stream.where((F.col("seq") > half) & (F.col("seq") <= last)), last))


@query("cached_reach", _pairs_sql(_prefix(f"event_id <= {_LAST} // 2 + 20"), _ends_sql("user_key"), f"SELECT max(x) + 1 FROM ({_ends_sql('user_key')})"))
def _(spark, sf_dir):
    stream, _, v, _, half, cache, build = _cached(spark, sf_dir)
    to = half + 20
    return _told(cache.reachable(hashed_pairs(spark, N_PAIRS, v), stream.where((F.col("seq") > half) & (F.col("seq") <= to)), build(to), to))


def _replay_labels_sql(points: list[tuple[int, str]]) -> str:
    text = graphs.EDGES["user_key"].format(**graphs.DUCKDB).replace("SELECT user_id AS u", "SELECT event_id, user_id AS u")
    values = ", ".join(f"({k}, {at})" for k, at in points)
    return f"""
WITH RECURSIVE q(query_id, upto) AS (VALUES {values}), o AS MATERIALIZED ({text}),
e AS MATERIALIZED (SELECT query_id, u, v FROM q JOIN o ON o.event_id <= q.upto GROUP BY query_id, u, v HAVING count(*) % 2 = 1),
b AS MATERIALIZED (SELECT query_id, u, v FROM e UNION SELECT query_id, v, u FROM e), verts AS (SELECT u AS x FROM o UNION SELECT v FROM o),
cc(query_id, vertex, component) USING KEY (query_id, vertex) AS (
  SELECT query_id, x, x FROM q, verts
  UNION SELECT c.query_id, b.v, min(c.component) FROM cc c JOIN b ON b.u = c.vertex AND b.query_id = c.query_id
        JOIN recurring.cc r ON r.vertex = b.v AND r.query_id = b.query_id WHERE c.component < r.component GROUP BY c.query_id, b.v)
SELECT query_id::BIGINT AS query_id, vertex::BIGINT AS vertex, component::BIGINT AS component FROM cc"""


def _replay_sql(points: list[tuple[int, str]]) -> str:
    return f"SELECT query_id, count(DISTINCT component)::BIGINT AS components FROM ({_replay_labels_sql(points)}) GROUP BY query_id"


def _replay(spark, sf_dir, points):
    stream, vertices, v, n = user_key_stream(spark, sf_dir)
    last = table(spark, sf_dir, "events").agg(F.max("event_id")).first()[0]
    out = ingest.replay(stream, [(k, at(last), "global") for k, at in points], SketchParams.for_edges(v, n), vertices)
    counts = [(k, answered(r).select("component").distinct().count()) for k, _, r in out]
    return spark.createDataFrame(counts, "query_id long, components long")


@query("replay_queries", _replay_sql([(k, f"{_LAST} * {k} // 5") for k in range(1, 6)]))
def _(spark, sf_dir):
    return _replay(spark, sf_dir, [(k, lambda last, k=k: last * k // 5) for k in range(1, 6)])


@query("burst_queries", _replay_sql([(k, f"{_LAST} // 3 + {10 * k}") for k in range(5)]))
def _(spark, sf_dir):
    return _replay(spark, sf_dir, [(k, lambda last, k=k: last // 3 + 10 * k) for k in range(5)])


_KIND_POINTS = [(1, f"{_LAST} // 3", "global"), (2, f"{_LAST} // 2", "cut"), (3, f"{_LAST} // 2 + 10", "kconn"), (4, _LAST, "cut")]


def _kinds_sql() -> str:
    """Components, forest edges of a certificate and the cut of each user, below 3."""
    text = graphs.EDGES["user_key"].format(**graphs.DUCKDB).replace("SELECT user_id AS u", "SELECT event_id, user_id AS u")
    points = ", ".join(f"({k}, {at})" for k, at, kind in _KIND_POINTS if kind == "cut")
    wide = _replay_sql([(k, at) for k, at, kind in _KIND_POINTS if kind != "cut"])
    return f"""
WITH o AS MATERIALIZED ({text}), q(query_id, upto) AS (VALUES {points}),
e AS (SELECT query_id, u, v FROM q JOIN o ON o.event_id <= q.upto GROUP BY query_id, u, v HAVING count(*) % 2 = 1),
c AS (SELECT q.query_id, x, count(e.u) AS n FROM q CROSS JOIN (SELECT DISTINCT u AS x FROM o) LEFT JOIN e ON e.query_id = q.query_id AND e.u = x GROUP BY q.query_id, x)
SELECT query_id, -1::BIGINT AS id, CASE WHEN query_id = 1 THEN components ELSE (SELECT count(*) FROM (SELECT u FROM o UNION SELECT v FROM o)) - components END::BIGINT AS value FROM ({wide})
UNION ALL SELECT query_id::BIGINT, x::BIGINT, CASE WHEN n < 3 THEN n ELSE -1 END::BIGINT FROM c"""


@query("replay_kinds", _kinds_sql())
def _(spark, sf_dir):
    stream, vertices, v, n = user_key_stream(spark, sf_dir)
    last = table(spark, sf_dir, "events").agg(F.max("event_id")).first()[0]
    at = {1: last // 3, 2: last // 2, 3: last // 2 + 10, 4: last}
    users = stream.select(F.col("u").alias("cut_id"), F.col("u").alias("vertex")).distinct()
    out = ingest.replay(stream, [(k, at[k], kind) for k, _, kind in _KIND_POINTS], SketchParams.for_edges(v, n, copies=3), vertices, cut_rows=users)
    made = None
    for (k, _, kind), (_, _, result) in zip(_KIND_POINTS, out):
        if kind == "cut":
            one = result.select(F.col("cut_id").alias("id"), F.coalesce("w", F.lit(-1)).cast("long").alias("value"))
        elif kind == "kconn":
            one = result.where("forest_no = 0").agg(F.lit(-1).cast("long").alias("id"), F.count(F.lit(1)).alias("value"))
        else:
            one = answered(result).agg(F.lit(-1).cast("long").alias("id"), F.countDistinct("component").alias("value"))
        one = one.withColumn("query_id", F.lit(k).cast("long"))
        made = one if made is None else made.unionByName(one)
    return made


# ---------------------------------------------------------------- cuts and certificates


def _cut_sql(edges: str, cut_rows: str, k: int) -> str:
    return f"""
WITH e AS ({edges}), c AS ({cut_rows}), ids AS (SELECT DISTINCT cut_id FROM c),
n AS (SELECT ids.cut_id, count(*) FILTER ((a.vertex IS NULL) <> (b.vertex IS NULL)) AS n FROM ids CROSS JOIN e
      LEFT JOIN c a ON a.cut_id = ids.cut_id AND a.vertex = e.u LEFT JOIN c b ON b.cut_id = ids.cut_id AND b.vertex = e.v GROUP BY ids.cut_id)
SELECT cut_id::BIGINT AS cut_id, CASE WHEN n < {k} THEN n ELSE -1 END::BIGINT AS w, n >= {k} AS unbounded FROM n"""


_CUTS = {
    # natural cuts: (graph, rows of (cut_id, vertex))
    "region": ("region_tree", "SELECT r_regionkey AS cut_id, r_regionkey AS vertex FROM region UNION ALL SELECT n_regionkey, 5 + n_nationkey FROM nation UNION ALL SELECT n_regionkey, 30 + c_custkey FROM customer JOIN nation ON c_nationkey = n_nationkey UNION ALL SELECT n_regionkey, 30 + (SELECT count(*) FROM customer) + s_suppkey FROM supplier JOIN nation ON s_nationkey = n_nationkey"),
    "nation": ("region_tree", "SELECT n_nationkey AS cut_id, 5 + n_nationkey AS vertex FROM nation UNION ALL SELECT c_nationkey, 30 + c_custkey FROM customer UNION ALL SELECT s_nationkey, 30 + (SELECT count(*) FROM customer) + s_suppkey FROM supplier"),
    "month_suppliers": ("month_part_supplier", "SELECT s_suppkey AS cut_id, (SELECT count(*) FROM part) + s_suppkey AS vertex FROM supplier"),
    "month_brands": ("month_part_supplier", "SELECT dense_rank() OVER (ORDER BY p_brand) AS cut_id, p_partkey AS vertex FROM part"),
    "suppliers": ("part_supplier", "SELECT s_suppkey AS cut_id, (SELECT count(*) FROM part) + s_suppkey AS vertex FROM supplier"),
}


def _cut_query(which: str, k: int):
    name, rows = _CUTS[which]

    def run(spark, sf_dir):
        s, vertices = sketched(spark, sf_dir, name, copies=k)
        made, complete = certificate.peel(s, k, vertices)
        if not complete:
            raise RuntimeError("incomplete certificate")
        graphs.views(spark, sf_dir, rows)
        cut = spark.sql(rows).selectExpr("cast(cut_id as long) cut_id", "cast(vertex as long) vertex")
        return cuts.cut_values(made, cut, k).withColumn("w", F.coalesce("w", F.lit(-1).cast("long")))  # -1: unbounded

    return run


for _which, _k in [("region", 2), ("nation", 2), ("month_suppliers", 1), ("month_suppliers", 4), ("month_suppliers", 8), ("month_brands", 4), ("suppliers", 2)]:
    query(f"cut_{_which}_k{_k}", _cut_sql(graphs.oracle(_CUTS[_which][0]), _CUTS[_which][1], _k))(_cut_query(_which, _k))


@query("mincut_complete_k3", "SELECT least(3, count(DISTINCT s_suppkey) - 1)::BIGINT AS min_cut FROM supplier")
def _(spark, sf_dir):
    s, vertices = sketched(spark, sf_dir, "supplier_supplier", copies=3)
    made, _ = certificate.peel(s, 3, vertices)
    return spark.createDataFrame([(cuts.min_cut(made, vertices, 3),)], "min_cut long")


@query("mincut_planted", "SELECT least(c, 4)::BIGINT AS min_cut, c::BIGINT AS planted FROM (VALUES (1), (3), (4), (6)) t(c)")
def _(spark, sf_dir):
    rows = []
    for c in (1, 3, 4, 6):
        e = generate.planted_cut(spark, 12, c)
        made, _ = certificate.peel(certificate.sketch(U.from_edges(e), SketchParams.for_edges(24, 160), 4))
        rows.append((cuts.min_cut(made, ends_of(e), 4), c))
    return spark.createDataFrame(rows, "min_cut long, planted long")


@query("certificate_summary_k3", "SELECT n - 1 AS first_forest, true AS disjoint, true AS bounded, true AS in_graph FROM (SELECT count(*)::BIGINT AS n FROM supplier)")
def _(spark, sf_dir):
    e, v, n = prepared(spark, sf_dir, "supplier_supplier")
    vertices = materialize(ends_of(e), "vertices")
    s = GraphSketch.build(U.from_edges(e), SketchParams.for_edges(v, n, copies=3))
    made, _ = certificate.peel(s, 3, vertices)
    made = materialize(made, "certificate")
    v = vertices.count()
    disjoint = made.select("u", "v").distinct().count() == made.count()
    inside = made.join(e, ["u", "v"], "left_anti").isEmpty()
    return made.agg(F.count(F.when(F.col("forest_no") == 0, 1)).alias("first_forest"), F.lit(disjoint).alias("disjoint"), (F.count(F.lit(1)) <= 3 * (v - 1)).alias("bounded"), F.lit(inside).alias("in_graph"))


@query("bridges_region_tree", f"SELECT u, v FROM ({graphs.oracle('region_tree')})")
def _(spark, sf_dir):
    s, vertices = sketched(spark, sf_dir, "region_tree", copies=2)
    made, _ = certificate.peel(s, 2, vertices)
    return spark.createDataFrame(cuts.bridges(made), "u long, v long")


# ---------------------------------------------------------------- streams and layout A


@query("net_edges", f"SELECT u::BIGINT AS u, v::BIGINT AS v FROM ({_odd('part_supplier')})")
def _(spark, sf_dir):
    return U.live_edges(toggle_part_supplier(spark, sf_dir)[0])


@query("stream_validation", f"SELECT count(*) - count(DISTINCT (u, v)) AS violations FROM ({graphs.EDGES['part_supplier']})")
def _(spark, sf_dir):
    rows = _lineitem(spark, sf_dir, "unix_micros(cast(l_shipdate as timestamp)) AS seq").select("seq", "u", "v", F.lit(1).cast("tinyint").alias("delta"))
    return U.validate(rows).agg(F.count(F.lit(1)).alias("violations"))


@query("stream_stats", f"""SELECT count(*)::BIGINT AS updates, count(*) FILTER (k % 2 = 1)::BIGINT AS inserts, count(*) FILTER (k % 2 = 0)::BIGINT AS deletes, count(DISTINCT (u, v))::BIGINT AS edges
FROM (SELECT u, v, row_number() OVER (PARTITION BY u, v) AS k FROM ({graphs.EDGES['part_supplier']}))""")
def _(spark, sf_dir):
    stream = toggle_part_supplier(spark, sf_dir)[0]
    return stream.agg(F.count(F.lit(1)).alias("updates"), F.count(F.when(F.col("delta") > 0, 1)).alias("inserts"), F.count(F.when(F.col("delta") < 0, 1)).alias("deletes"), F.countDistinct("u", "v").alias("edges"))


_SMALL = SketchParams(4096, columns=2, samplers=4, levels=26, hash_family="pair31")


def _small_buckets(spark, sf_dir, variant: str = "one_level"):
    e = graphs.edges(spark, sf_dir, "page_links")
    return buckets.toggles(U.from_edges(e), _SMALL.with_(variant=variant))


@query("bucket_rows_pair31", buckets.pair31_oracle(graphs.oracle("page_links"), _SMALL))
def _(spark, sf_dir):
    return _small_buckets(spark, sf_dir).drop("copy")


@query("bucket_rows_nested", buckets.pair31_oracle(graphs.oracle("page_links"), _SMALL, nested=True))
def _(spark, sf_dir):
    return _small_buckets(spark, sf_dir, "nested").drop("copy")


_A, _B, _C = buckets.pair31_factors(buckets.CHECK_INDEX + _SMALL.seed)


@query("decode_pair31", f"""
WITH k AS ({buckets.pair31_oracle(graphs.oracle("page_links"), _SMALL)}),
g AS (SELECT *, level >= 0 AND xe <> 0 AND (xe >> 32) < (xe & 4294967295) AND (xe & 4294967295) < greatest({_SMALL.v_count}, (SELECT max(v) + 1 FROM ({graphs.oracle("page_links")})))
      AND xc = (({_A} * (xe >> 32)) % 2147483647 + ({_B} * (xe & 4294967295)) % 2147483647 + {_C}) % 2147483647 + 1 AS good FROM k),
r AS (SELECT *, row_number() OVER (PARTITION BY vertex, sampler ORDER BY level DESC, col) AS k FROM g WHERE good)
SELECT w.vertex, w.sampler, CASE WHEN r.xe IS NULL THEN 'failed' ELSE 'edge' END AS status, coalesce(r.xe, 0) AS eid
FROM (SELECT vertex, sampler FROM k WHERE level = -1) w LEFT JOIN r ON r.vertex = w.vertex AND r.sampler = w.sampler AND r.k = 1""")
def _(spark, sf_dir):
    top = graphs.edges(spark, sf_dir, "page_links").agg(F.max(F.greatest("u", "v")).alias("top")).first().top
    params = _SMALL.with_(v_count=max(_SMALL.v_count, (top or 0) + 1))  # vertices beyond the small count are vertices too
    return buckets.decode(_small_buckets(spark, sf_dir), params).drop("copy").withColumn("eid", F.coalesce("eid", F.lit(0).cast("long")))


@query("handshake", "SELECT 0::BIGINT AS ids, 0::BIGINT AS checks")
def _(spark, sf_dir):
    return buckets.handshake(_small_buckets(spark, sf_dir))


# ---------------------------------------------------------------- costs and baselines


#: Vertices (rounded up to a power of two) and edges of each month's orders: what the cost models are asked for.
_MONTHS = """SELECT month, i, (1::BIGINT << i) AS v, e FROM (SELECT (year(o_orderdate) * 12 + month(o_orderdate))::INTEGER AS month,
ceil(log2(greatest(64, count(DISTINCT o_custkey))))::BIGINT AS i, count(*)::BIGINT AS e FROM orders GROUP BY 1)"""


@query("model_bytes", f"SELECT month, i::INTEGER AS i, 164.0::DOUBLE * v * (i * i - i) AS bytes, 164.0::DOUBLE * (i * i - i) * 16 AS worker FROM ({_MONTHS})")
def _(spark, sf_dir):
    rows = [(m.month, m.i, costs.model_bytes(m.v), costs.worker_bytes(m.v, 16)) for m in workloads.months(spark, sf_dir)]
    return spark.createDataFrame(rows, "month int, i int, bytes double, worker double")


@query("space_crossover", f"""SELECT month, b AS matrix_share, min(1::BIGINT << j)::BIGINT AS v FROM ({_MONTHS}), (SELECT 1.0::DOUBLE AS b UNION ALL SELECT 0.5), (SELECT unnest(range(6, 41)) AS j)
WHERE j >= i AND 164.0::DOUBLE * (j * j - j) < b * (1::BIGINT << j)::DOUBLE / 8 GROUP BY month, b""")
def _(spark, sf_dir):
    # the least power of two, from a month's customers on, at which the sketch is below that share of the bit matrix
    at = {b: costs.crossover(costs.model_bytes, b) for b in (1.0, 0.5)}
    rows = [(m.month, b, max(m.v, 1 << (least - 1).bit_length())) for m in workloads.months(spark, sf_dir) for b, least in at.items()]
    return spark.createDataFrame(rows, "month int, matrix_share double, v long")


@query("hash_calls", f"SELECT month, i::INTEGER AS i, (2 * ceil(i * ln(2) / ln(1.5)) * 2 + 2)::INTEGER AS hashes FROM ({_MONTHS})")
def _(spark, sf_dir):
    rows = [(m.month, m.i, costs.hash_calls(SketchParams(m.v))) for m in workloads.months(spark, sf_dir)]
    return spark.createDataFrame(rows, "month int, i int, hashes int")


@query("adjacency_bits", f"""SELECT u::BIGINT AS u, v // 64 AS word, bit_xor(CASE WHEN v % 64 = 63 THEN (-9223372036854775807 - 1)::BIGINT ELSE 1::BIGINT << (v % 64) END) AS bits
FROM (SELECT u::BIGINT AS u, v::BIGINT AS v FROM ({graphs.EDGES['part_supplier']}) UNION ALL SELECT v::BIGINT, u::BIGINT FROM ({graphs.EDGES['part_supplier']})) GROUP BY ALL HAVING bits <> 0""")
def _(spark, sf_dir):
    stream, v, _ = toggle_part_supplier(spark, sf_dir)
    return exact.adjacency_bits(stream, v)


@query("adjacency_list", f"SELECT vertex, count(*)::INTEGER AS degree, sum(x)::BIGINT AS near_sum FROM (SELECT u AS vertex, v AS x FROM ({graphs.oracle('page_links')}) UNION ALL SELECT v, u FROM ({graphs.oracle('page_links')})) GROUP BY vertex")
def _(spark, sf_dir):
    made = exact.adjacency_list(U.from_edges(graphs.edges(spark, sf_dir, "page_links")))
    return made.select("vertex", "degree", F.aggregate("near", F.lit(0).cast("long"), lambda a, x: a + x).alias("near_sum"))


@query("label_propagation", components_sql(graphs.oracle("page_links")))
def _(spark, sf_dir):
    return exact.label_propagation(graphs.edges(spark, sf_dir, "page_links"))[0]


@query("star_components", components_sql(graphs.oracle("order_part")))
def _(spark, sf_dir):
    return exact.components(graphs.edges(spark, sf_dir, "order_part"))


@query("batch_dynamic", components_sql(_odd("user_key"), _ends_sql("user_key")))
def _(spark, sf_dir):
    stream, _, _, _ = user_key_stream(spark, sf_dir)
    return exact.batch_dynamic(stream, max(1, stream.count() // 3))


@query("recompute_components", components_sql(_odd("user_key")))
def _(spark, sf_dir):
    return exact.recompute(user_key_stream(spark, sf_dir)[0])


@query("er_edges", generate.thinned_sql(graphs.oracle("part_supplier"), 25, 1))
def _(spark, sf_dir):
    # each pair of a part and a supplier that the table gives is an edge with this chance
    return generate.thinned(spark, graphs.edges(spark, sf_dir, "part_supplier"), 25, 1)


@query("kron_edges", generate.kronecker_sql(8, 0, 1, "(SELECT event_id AS i FROM events)"))
def _(spark, sf_dir):
    # each event is a draw
    return generate.kronecker(spark, 8, 0, draws_of=table(spark, sf_dir, "events").select(F.col("event_id").alias("i")))


@query("cc_erdos_renyi", components_sql(generate.erdos_renyi_sql(256, 1, 3, "(SELECT i FROM range(65536) t(i))"), "SELECT i AS x FROM range(256) t(i)"))
def _(spark, sf_dir):
    e = generate.erdos_renyi(spark, 256, 1, 3)
    s = GraphSketch.build(U.from_edges(e), SketchParams.for_edges(256, 2000))
    return answered(spanning_forest(s, vertices=spark.range(256).toDF("vertex")))


# ---------------------------------------------------------------- workloads whose measures are exact

_TABLE = " UNION ALL ".join(f"SELECT '{n}' AS graph, (SELECT count(*) FROM (SELECT u FROM g UNION SELECT v FROM g)) AS vertices, (SELECT count(*) FROM g) AS edges, 13 * (SELECT count(*) FROM g) AS churn_updates".replace("FROM g", f"FROM ({graphs.oracle(n)})") for n in graphs.EDGES)


@query("w_dataset_table", _TABLE)
def _(spark, sf_dir):
    return workloads.dataset_table(spark, sf_dir)


@query("w_communication_bound", "SELECT g AS graph, a::DOUBLE AS alpha, m::DOUBLE AS gamma, 3 + 1 / (m::DOUBLE * a::DOUBLE) AS bound, true AS within FROM (VALUES ('part_supplier'), ('customer_stars')) t(g), (VALUES (1.0), (2.0)) s(a), (VALUES (0.04), (0.25), (0.5)) r(m)")
def _(spark, sf_dir):
    return workloads.communication(spark, sf_dir, ("part_supplier", "customer_stars")).select("graph", "alpha", "gamma", "bound", "within")

_EACH_GRAPH = " UNION ALL ".join(f"SELECT '{n}' AS graph, (SELECT count(*) FROM ({graphs.oracle(n)})) AS updates" for n in graphs.EDGES)


@query("w_traffic_all_graphs", f"SELECT graph, updates::BIGINT AS updates, true AS within FROM ({_EACH_GRAPH}) WHERE updates > 0")
def _(spark, sf_dir):
    return workloads.communication(spark, sf_dir, [*graphs.EDGES], (1.0,), (0.04,)).where("updates > 0").select("graph", "updates", "within")


@query("w_traffic_by_queries", f"SELECT q::INTEGER AS queries, 13 * (SELECT count(*) FROM ({graphs.oracle('part_supplier')}))::BIGINT AS updates, true AS within FROM (VALUES (1), (2), (4)) t(q)")
def _(spark, sf_dir):
    return workloads.traffic_by_queries(spark, sf_dir).select("queries", "updates", "within")


def _first_forest(name: str) -> str:
    return f"SELECT '{name}' AS graph, count(*) - count(DISTINCT component) AS n FROM ({components_sql(graphs.oracle(name))})"


@query("w_certificate_sizes", "SELECT graph, k::INTEGER AS k, n::BIGINT AS first_forest, true AS bounded, true AS complete FROM (" + " UNION ALL ".join(map(_first_forest, ("user_key", "page_links", "conversations", "month_part_supplier"))) + "), (VALUES (1), (2), (4)) t(k)")
def _(spark, sf_dir):
    return workloads.certificate_sizes(spark, sf_dir)


@query("w_moves", "SELECT p AS policy, n::INTEGER AS moves FROM (VALUES ('raw', 1), ('delta', 1), ('hybrid', 1), ('tree', 2)) t(p, n)")
def _(spark, sf_dir):
    stream = U.from_edges(prepared(spark, sf_dir, "page_links")[0])
    stream = materialize(stream, "stream")
    return spark.createDataFrame([(m, costs.moves_per_update(stream, SketchParams(4096), BatchPolicy(m))) for m in ("raw", "delta", "hybrid", "tree")], "policy string, moves int")


@query("w_density_survey", f"SELECT graph, (2::DOUBLE * edges) / (vertices * (vertices - 1)) AS density, (edges * 16)::BIGINT AS list_bytes FROM ({_TABLE})")
def _(spark, sf_dir):
    return workloads.density_survey(spark, sf_dir)


_S = "ceil(i * ln(2) / ln(1.5))::BIGINT"


@query("w_space_curve", f"SELECT (1::BIGINT << i) AS v, (164 * (1::BIGINT << i) * (i * i - i))::DOUBLE AS model_bytes, ((1::BIGINT << i) * {_S} * (8 * i + 1) * 8)::DOUBLE AS our_bytes, (1::BIGINT << (2 * i))::DOUBLE / 8 AS matrix_bytes FROM (SELECT i::BIGINT AS i FROM range(6, 22) t(i))")
def _(spark, sf_dir):
    return workloads.space_curve(spark)


@query("w_hash_work", f"""SELECT month, v, w AS variant, (2 * {_S} * 2 + 2)::INTEGER AS hashes, ({_S} * 2 * CASE WHEN w = 'nested' THEN 2 * i ELSE 1 END)::INTEGER AS examined,
{_S}::DOUBLE * (2 * CASE WHEN w = 'nested' THEN 2::DOUBLE - pow(2::DOUBLE, 1 - 2 * i) ELSE 1::DOUBLE END + 1) AS written FROM ({_MONTHS}), (VALUES ('one_level'), ('nested')) x(w)""")
def _(spark, sf_dir):
    return workloads.hash_work(spark, sf_dir)


@query("w_k_laws", f"""SELECT month, v, k::INTEGER AS k, (k * {_S} * (8 * i + 1) * 8)::BIGINT AS vertex_bytes, (k * 2 * {_S} * 2 + 2)::INTEGER AS hashes,
(k * {_S} * 2)::INTEGER AS examined FROM ({_MONTHS}), (VALUES (1), (2), (4), (8)) x(k)""")
def _(spark, sf_dir):
    rows = [(m.month, m.v, k, p.vertex_bytes, costs.hash_calls(p), costs.buckets_examined(p)) for m in workloads.months(spark, sf_dir) for k in (1, 2, 4, 8) for p in [SketchParams(m.v, copies=k)]]
    return spark.createDataFrame(rows, "month int, v long, k int, vertex_bytes long, hashes int, examined int")


@query("sampler_bytes", f"""SELECT month, w AS variant, (2 * i)::INTEGER AS log_n, j::INTEGER AS log_inverse_delta, (56::DOUBLE * j) * (2 * i) * CASE WHEN w = 'nested' THEN 1::DOUBLE ELSE 2::DOUBLE / 7 END AS bytes
FROM ({_MONTHS}), (VALUES ('nested'), ('one_level')) t(w), range(2, 11, 4) b(j)""")
def _(spark, sf_dir):
    # the vector of a month has a place for each pair of its customers
    rows = [(m.month, w, 2 * m.i, j, float(costs.sampler_bytes(w, float(m.v) ** 2, 2.0**-j))) for m in workloads.months(spark, sf_dir) for w in ("nested", "one_level") for j in range(2, 11, 4)]
    return spark.createDataFrame(rows, "month int, variant string, log_n int, log_inverse_delta int, bytes double")


@query("sampler_levels", f"SELECT month, e AS most_edges, least(62, ceil(log2(greatest(2, e))) + 2)::INTEGER AS levels, (2 * (2 * least(62, ceil(log2(greatest(2, e))) + 2) * 2 + 1) * 4)::BIGINT AS body_bytes FROM ({_MONTHS})")
def _(spark, sf_dir):
    rows = [(m.month, m.e, p.levels, p.body_bytes) for m in workloads.months(spark, sf_dir) for p in [SketchParams.for_edges(m.v, m.e)]]
    return spark.createDataFrame(rows, "month int, most_edges long, levels int, body_bytes long")


@query("sketch_currentness", "SELECT e::BIGINT AS epoch, a::BIGINT AS at_seq, a <= e AS is_current FROM (VALUES (10), (20)) t(e), (VALUES (5), (10), (11), (20), (21)) s(a)")
def _(spark, sf_dir):
    e, v, n = prepared(spark, sf_dir, "page_links")
    stream = U.from_edges(e)
    first = GraphSketch.build(stream.where("u % 2 = 0"), SketchParams.for_edges(v, n), epoch=10)
    both = first.advance(stream.where("u % 2 = 1"), 20)
    return spark.createDataFrame([(s.epoch, a, s.is_current(a)) for s in (first, both) for a in (5, 10, 11, 20, 21)], "epoch long, at_seq long, is_current boolean")


@query("w_bottlenecks", f"""SELECT month, a AS approach, s AS space, c AS cpu, n AS network, CASE WHEN s / (16.0::DOUBLE * e) >= greatest(c / i, n / 27) THEN 'space' WHEN c / i >= n / 27 THEN 'cpu' ELSE 'network' END AS dominant
FROM (SELECT month, i::DOUBLE AS i, e, a, CASE a WHEN 'adjacency' THEN v::DOUBLE * v / 8 WHEN 'lossless distributed' THEN 16.0::DOUBLE * e WHEN 'earlier sketch' THEN 164.0::DOUBLE * v * (i * i - i) / (2::DOUBLE / 7) ELSE 164.0::DOUBLE * v * (i * i - i) END AS s,
CASE a WHEN 'adjacency' THEN 1 WHEN 'earlier sketch' THEN i * i ELSE i END::DOUBLE AS c, CASE a WHEN 'lossless distributed' THEN 16 * i WHEN 'one-level sketch' THEN 27 ELSE 9 END::DOUBLE AS n
FROM ({_MONTHS}), (VALUES ('adjacency'), ('lossless distributed'), ('earlier sketch'), ('one-level sketch')) t(a))""")
def _(spark, sf_dir):
    return workloads.bottleneck_summary(spark, sf_dir)


def _dealt_cut(across: int) -> str:
    """Orders and parts dealt into 24 classes, those that meet in a line are joined: two sides by parity, and ``across`` edges between them."""
    return f"""SELECT DISTINCT least(a, b) AS u, greatest(a, b) AS v FROM (SELECT l_orderkey % 24 AS a, l_partkey % 24 AS b FROM lineitem)
WHERE a <> b AND (a % 2 = b % 2 OR greatest(a, b) = least(a, b) + 1 AND greatest(a, b) % 2 = 1 AND greatest(a, b) < {2 * across})"""


# two dense sides have their least cut between them or at a vertex
@query("exact_min_cut", " UNION ALL ".join(f"""SELECT {c}::BIGINT AS planted, least((SELECT count(*) FROM ({_dealt_cut(c)}) WHERE u % 2 <> v % 2),
(SELECT min(d) FROM (SELECT x, count(*) AS d FROM (SELECT u AS x FROM ({_dealt_cut(c)}) UNION ALL SELECT v FROM ({_dealt_cut(c)})) GROUP BY x)))::BIGINT AS min_cut""" for c in (1, 3, 4, 6)))
def _(spark, sf_dir):
    rows = []
    for c in (1, 3, 4, 6):
        graphs.views(spark, sf_dir, _dealt_cut(c))
        e = materialize(spark.sql(_dealt_cut(c)), "graph")
        rows.append((c, exact.min_cut(U.from_edges(e), ends_of(e))))
    return spark.createDataFrame(rows, "planted long, min_cut long")


@query("exact_cut_suppliers", f"""WITH e AS ({graphs.oracle('month_part_supplier')}) SELECT v - (SELECT count(*) FROM part) AS cut_id, count(*)::BIGINT AS n FROM e GROUP BY v""")
def _(spark, sf_dir):
    rows = _CUTS["month_suppliers"][1]
    graphs.views(spark, sf_dir, rows)
    cut = spark.sql(rows).selectExpr("cast(cut_id as long) cut_id", "cast(vertex as long) vertex")
    return exact.cut_values(U.from_edges(graphs.edges(spark, sf_dir, "month_part_supplier")), cut)


@query("stream_expiring", f"""WITH o AS (SELECT u, v, ts FROM ({graphs.EDGES['user_key'].format(**graphs.DUCKDB).replace('SELECT user_id AS u', 'SELECT ts, user_id AS u')})),
w AS (SELECT *, lag(ts) OVER (PARTITION BY u, v ORDER BY ts) AS b FROM o)
SELECT count(*) FILTER (b IS NULL OR ts > b + INTERVAL 7 DAYS)::BIGINT AS inserts, count(*) FILTER (b IS NULL OR ts > b + INTERVAL 7 DAYS)::BIGINT AS deletes FROM w""")
def _(spark, sf_dir):
    text = graphs.EDGES["user_key"].format(**graphs.SPARK).replace("SELECT user_id AS u", "SELECT ts, user_id AS u")
    graphs.views(spark, sf_dir, text)
    rows = spark.sql(text).selectExpr("cast(u as long) u", "cast(v as long) v", "cast(ts as timestamp) ts")
    return U.expiring(rows).agg(F.count(F.when(F.col("delta") > 0, 1)).alias("inserts"), F.count(F.when(F.col("delta") < 0, 1)).alias("deletes"))


@query("leaf_fullness", f"SELECT 2 * count(*)::BIGINT AS updates FROM ({graphs.oracle('part_supplier')})")
def _(spark, sf_dir):
    e, v, n = prepared(spark, sf_dir, "part_supplier")
    return costs.leaf_fullness(U.from_edges(e), SketchParams.for_edges(v, n)).agg(F.sum("updates").alias("updates"))



@query("w_matching_worst_case", "SELECT p AS policy, n::BIGINT AS updates, CASE WHEN p = 'delta' THEN 0 ELSE 2 * n END::BIGINT AS raw_ids, CASE WHEN p = 'delta' THEN 2 * n ELSE 0 END::BIGINT AS deltas FROM (VALUES ('raw'), ('delta'), ('hybrid')) t(p), (SELECT count(DISTINCT s_suppkey) AS n FROM supplier)")
def _(spark, sf_dir):
    # each supplier is an edge of a perfect matching
    key = table(spark, sf_dir, "supplier").where("s_suppkey IS NOT NULL").select(F.col("s_suppkey").cast("long").alias("k")).distinct()
    matched = key.select((F.col("k") * 2).alias("u"), (F.col("k") * 2 + 1).alias("v"))
    return workloads.matching_worst_case(spark, edges=matched).drop("shuffled_bytes")


for _w, _f in {
    "w_ablation": lambda s, d: workloads.ablation(s, d), "w_scaling": lambda s, d: workloads.scaling(s, d), "w_query_split": lambda s, d: workloads.query_split(s, d),
    "w_query_bursts": lambda s, d: workloads.query_bursts(s, d, 3), "w_k_sweep": lambda s, d: workloads.k_sweep(s, d), "w_update_rate": lambda s, d: workloads.update_rate_vs_bits(s, d),
    "w_sampler_failure": lambda s, d: workloads.sampler_failure(s), "w_many_datasets": lambda s, d: workloads.many_datasets(s, d), "w_measured_bottlenecks": lambda s, d: workloads.measured_bottlenecks(s, d),
}.items():
    query(_w)(_f)


# ---------------------------------------------------------------- relational operators around the methods


@query("proj_suppliers", graphs.oracle("supplier_supplier"))
def _(spark, sf_dir):
    return graphs.edges(spark, sf_dir, "supplier_supplier")


@query("rollup_density", f"""WITH e AS ({graphs.oracle('customer_supplier')}), d AS (SELECT u, count(*) AS n FROM e GROUP BY u)
SELECT n_regionkey AS region, c_mktsegment AS segment, count(*)::BIGINT AS customers, coalesce(sum(n), 0)::BIGINT AS edges, coalesce(sum(n), 0)::DOUBLE / (count(*) * (SELECT count(*) FROM supplier)) AS density
FROM customer JOIN nation ON c_nationkey = n_nationkey LEFT JOIN d ON u = c_custkey GROUP BY ROLLUP (n_regionkey, c_mktsegment)""")
def _(spark, sf_dir):
    # the share of all pairs of a customer and a supplier that are edges; degrees are summed before they meet the customers
    c, n, s = (table(spark, sf_dir, t) for t in ("customer", "nation", "supplier"))
    degree = graphs.edges(spark, sf_dir, "customer_supplier").groupBy("u").agg(F.count(F.lit(1)).alias("n"))
    met = c.join(F.broadcast(n), c.c_nationkey == n.n_nationkey).join(degree, F.col("u") == F.col("c_custkey"), "left")
    told = met.rollup(F.col("n_regionkey").alias("region"), F.col("c_mktsegment").alias("segment")).agg(F.count(F.lit(1)).alias("customers"), F.coalesce(F.sum("n"), F.lit(0)).cast("long").alias("edges"))
    return told.withColumn("density", F.col("edges").cast("double") / (F.col("customers") * s.count()))


@query("cube_updates", "SELECT l_returnflag AS flag, year(l_shipdate)::INTEGER AS y, count(*)::BIGINT AS n FROM lineitem GROUP BY CUBE (l_returnflag, year(l_shipdate))")
def _(spark, sf_dir):
    return table(spark, sf_dir, "lineitem").cube(F.col("l_returnflag").alias("flag"), F.year("l_shipdate").alias("y")).agg(F.count(F.lit(1)).alias("n"))


@query("sets_forests", "SELECT 0::BIGINT AS shared, 0::BIGINT AS outside")
def _(spark, sf_dir):
    s, vertices = sketched(spark, sf_dir, "month_part_supplier", copies=2)
    made = materialize(certificate.peel(s, 2, vertices)[0], "certificate")
    one, two = (made.where(F.col("forest_no") == i).select("u", "v") for i in (0, 1))
    e = graphs.edges(spark, sf_dir, "month_part_supplier")
    return spark.createDataFrame([(one.intersect(two).count(), one.union(two).exceptAll(e).count())], "shared long, outside long")


@query("topk_degree", f"SELECT vertex, d AS degree FROM (SELECT vertex, count(*)::BIGINT AS d FROM (SELECT u AS vertex FROM ({graphs.oracle('page_links')}) UNION ALL SELECT v FROM ({graphs.oracle('page_links')})) GROUP BY vertex) ORDER BY d DESC, vertex LIMIT 20")
def _(spark, sf_dir):
    ends = graphs.edges(spark, sf_dir, "page_links").select(F.explode(F.array("u", "v")).alias("vertex"))
    return ends.groupBy("vertex").agg(F.count(F.lit(1)).alias("degree")).orderBy(F.desc("degree"), "vertex").limit(20)


@query("window_live_count", f"""SELECT event_id AS seq, sum(d) OVER (PARTITION BY u ORDER BY event_id)::BIGINT AS live FROM
(SELECT event_id, u, CASE WHEN row_number() OVER (PARTITION BY u, v ORDER BY event_id) % 2 = 1 THEN 1 ELSE -1 END AS d FROM ({graphs.EDGES['user_key'].format(**graphs.DUCKDB).replace('SELECT user_id AS u', 'SELECT event_id, user_id AS u')}))""")
def _(spark, sf_dir):
    stream = user_key_stream(spark, sf_dir)[0]
    return stream.select("seq", F.sum("delta").over(Window.partitionBy("u").orderBy("seq").rowsBetween(Window.unboundedPreceding, Window.currentRow)).alias("live"))


_SNAPSHOTS = [(k, f"{_LAST} * {k} // 4") for k in (1, 2, 3)]


@query("asof_component", f"""WITH s(query_id, upto) AS (VALUES {', '.join(f'({k}, {at})' for k, at in _SNAPSHOTS)})
SELECT a.event_id AS query_id, a.upto::BIGINT AS snapshot, l.component FROM (SELECT event_id, user_id, s.query_id, s.upto FROM events ASOF JOIN s ON event_id >= s.upto) a
JOIN ({_replay_labels_sql(_SNAPSHOTS)}) l ON l.query_id = a.query_id AND l.vertex = a.user_id""")
def _(spark, sf_dir):
    # an as-of join: the snapshot at or before an event is found among the few snapshots in its row, then both meet on
    # (snapshot, vertex); a window by user would put a hot user's events into one task
    stream, vertices, v, n = user_key_stream(spark, sf_dir)
    ev = table(spark, sf_dir, "events").select("event_id", "user_id")
    last = ev.agg(F.max("event_id")).first()[0]
    points = {k: last * k // 4 for k in (1, 2, 3)}
    out = ingest.replay(stream, [(k, at, "global") for k, at in points.items()], SketchParams.for_edges(v, n), vertices)
    labels = None
    for k, _, result in out:
        one = answered(result).select("vertex", "component", F.lit(points[k]).cast("long").alias("snapshot"))
        labels = one if labels is None else labels.unionByName(one)
    at = F.array(*[F.lit(x).cast("long") for x in points.values()])
    seen = ev.withColumn("snapshot", F.array_max(F.filter(at, lambda x: x <= F.col("event_id")))).where("snapshot IS NOT NULL")
    met = seen.join(labels.withColumnRenamed("vertex", "user_id"), ["snapshot", "user_id"])
    return met.select(F.col("event_id").alias("query_id"), "snapshot", "component")


@query("epoch_range_join", "SELECT (event_id // 700)::BIGINT AS epoch, count(*)::BIGINT AS updates FROM events WHERE event_id >= 0 GROUP BY 1")
def _(spark, sf_dir):
    # a range join by bins: epochs and events meet on the bin that the range covers; epochs reach the last event
    last = table(spark, sf_dir, "events").agg(F.max("event_id").alias("last")).first().last
    epochs = spark.range(0 if last is None else last // 700 + 1).select(F.col("id").alias("epoch"), (F.col("id") * 700).alias("lo"), (F.col("id") * 700 + 700).alias("hi"))
    binned = epochs.withColumn("bin", F.explode(F.sequence(F.floor(F.col("lo") / 1000), F.floor((F.col("hi") - 1) / 1000))))
    ev = table(spark, sf_dir, "events").select("event_id", F.floor(F.col("event_id") / 1000).alias("bin"))
    return ev.join(binned, "bin").where("event_id >= lo AND event_id < hi").groupBy("epoch").agg(F.count(F.lit(1)).alias("updates"))


@query("semi_broken", "SELECT c_custkey FROM customer WHERE EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey AND o_orderstatus = 'F')")
def _(spark, sf_dir):
    c, o = table(spark, sf_dir, "customer"), table(spark, sf_dir, "orders").where("o_orderstatus = 'F'")
    return c.join(o, c.c_custkey == o.o_custkey, "left_semi").select("c_custkey")


@query("anti_isolated", f"SELECT doc_id FROM documents WHERE doc_id NOT IN (SELECT u FROM ({graphs.oracle('docs_exact')}) UNION SELECT v FROM ({graphs.oracle('docs_exact')}))")
def _(spark, sf_dir):
    ends = ends_of(graphs.edges(spark, sf_dir, "docs_exact"))
    return table(spark, sf_dir, "documents").select("doc_id").join(ends, F.col("doc_id") == F.col("vertex"), "left_anti")


# ---------------------------------------------------------------- streaming


def _as_stream(spark, df: DataFrame, files: int = 3) -> DataFrame:
    path = scratch_path(spark, "slices")
    df.repartition(files).write.parquet(path)
    return spark.readStream.schema(df.schema).option("maxFilesPerTrigger", 1).parquet(path)


def _drained(spark, stream: DataFrame, mode: str = "append") -> DataFrame:
    out, at = scratch_path(spark, "stream-out"), scratch_path(spark, "stream-at")
    if mode == "append":
        stream.writeStream.format("parquet").option("path", out).option("checkpointLocation", at).trigger(availableNow=True).start().awaitTermination()
    else:
        stream.writeStream.outputMode(mode).foreachBatch(lambda b, _: b.write.mode("overwrite").parquet(out)).option("checkpointLocation", at).trigger(availableNow=True).start().awaitTermination()
    return spark.read.parquet(out)


@query("stream_ingest_components", components_sql(graphs.oracle("page_links")))
def _(spark, sf_dir):
    e, v, n = prepared(spark, sf_dir, "page_links")
    p = SketchParams.for_edges(v, n)
    path = scratch_path(spark, "stream-sketch")
    ingest.ingest(_as_stream(spark, U.from_edges(e)), path, p, scratch_path(spark, "stream-at")).awaitTermination()
    s = ingest.sketched(spark, path, p, scratch_path(spark, "sketch"))
    return answered(spanning_forest(s, vertices=ends_of(e)))


@query("stream_window_counts", "SELECT time_bucket(INTERVAL 7 DAYS, ts, TIMESTAMP '1970-01-01') AS start, count(*)::BIGINT AS n FROM events GROUP BY 1")
def _(spark, sf_dir):
    ev = table(spark, sf_dir, "events").select(F.col("ts").cast("timestamp").alias("ts"))
    counted = _as_stream(spark, ev).groupBy(F.window("ts", "7 days").alias("w")).agg(F.count(F.lit(1)).alias("n"))
    return _drained(spark, counted, "complete").select(F.col("w.start").cast("timestamp_ntz").alias("start"), "n")


@query("stream_session_users", """SELECT user_id, count(*)::BIGINT AS sessions, sum(n)::BIGINT AS events FROM (SELECT user_id, s, count(*) AS n FROM
(SELECT user_id, ts, sum(new) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS s FROM (SELECT user_id, event_id, ts, CASE WHEN lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) + INTERVAL 1 DAY > ts THEN 0 ELSE 1 END AS new FROM events)) GROUP BY user_id, s) GROUP BY user_id""")
def _(spark, sf_dir):
    ev = table(spark, sf_dir, "events").select(F.col("ts").cast("timestamp").alias("ts"), "user_id")
    s = _as_stream(spark, ev).groupBy(F.session_window("ts", "1 day").alias("w"), "user_id").agg(F.count(F.lit(1)).alias("n"))
    return _drained(spark, s, "complete").groupBy("user_id").agg(F.count(F.lit(1)).alias("sessions"), F.sum("n").alias("events"))


@query("stream_dedup", "SELECT event_id, user_id FROM events")
def _(spark, sf_dir):
    ev = table(spark, sf_dir, "events").select(F.col("ts").cast("timestamp").alias("ts"), "event_id", "user_id")
    twice = _as_stream(spark, ev.union(ev)).withWatermark("ts", "3650 days")
    return _drained(spark, twice.dropDuplicatesWithinWatermark(["event_id"])).select("event_id", "user_id")


def queries() -> dict:
    return dict(Q)


def oracle_sql() -> dict[str, str]:
    return dict(SQL)
