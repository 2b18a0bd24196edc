"""Queries of the methods, their variants, rivals and measures on the given tables."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window, functions as F

from ..joins import key_join
from ..model import BipartiteGraph, to_traversals
from ..operators import agreement, cocluster, criterion, greedy, hierarchy, implicit, ingest, modularity, mutual, network, rivals, routing, similarity, weights
from ..scratch import materialise, new_path
from ..sources import tables
from ..sources.tables import table
from .registry import Catalog

catalog = Catalog()
add = catalog.add

G3 = """SELECT o_custkey AS t, l_partkey AS s, count(*) AS n, max(p_size)::DOUBLE AS length
FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN part ON l_partkey = p_partkey GROUP BY 1, 2"""
G4 = "SELECT l_orderkey AS t, l_suppkey AS s, count(*) AS n, 1.0::DOUBLE AS length FROM lineitem GROUP BY 1, 2"
_TRIPS = """WITH g AS (SELECT user_id, event_id, ts, json_extract(props, '$.k')::INT AS k, CASE WHEN ts - lag(ts) OVER w > INTERVAL 24 HOUR OR lag(ts) OVER w IS NULL THEN 1 ELSE 0 END AS new FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)), x AS (SELECT *, (sum(new) OVER (PARTITION BY user_id ORDER BY ts, event_id) - 1)::BIGINT AS trip FROM g)"""
_G5 = _TRIPS + " SELECT user_id * 1000000 + trip AS t, k::BIGINT AS s, count(*) AS n, 1.0::DOUBLE AS length FROM x GROUP BY 1, 2"
G8 = """SELECT c_nationkey::BIGINT AS t, s_nationkey::BIGINT AS s, count(*) AS n FROM lineitem JOIN orders ON l_orderkey = o_orderkey
JOIN customer ON o_custkey = c_custkey JOIN supplier ON l_suppkey = s_suppkey GROUP BY 1, 2"""


def spatial_sql(graph: str) -> str:
    return f"""WITH e AS ({graph}), d AS (SELECT s, ln((SELECT count(DISTINCT t) FROM e)::DOUBLE / count(*)) AS idf FROM e GROUP BY s)
SELECT t AS v, e.s AS f, round(n * length / sum(n * length) OVER (PARTITION BY t) * idf, 6) AS w FROM e JOIN d ON e.s = d.s"""


def visit_sql(graph: str) -> str:
    return f"""WITH e AS ({graph}), d AS (SELECT t, ln((SELECT count(DISTINCT s) FROM e)::DOUBLE / count(*)) AS idf FROM e GROUP BY t)
SELECT s AS v, e.t AS f, round(n::DOUBLE / sum(n) OVER (PARTITION BY s) * idf, 6) AS w FROM e JOIN d ON e.t = d.t"""


def rounded(df: DataFrame, *columns: str, to: int = 6) -> DataFrame:
    return df.withColumns({c: F.round(c, to) for c in columns})


@add(spatial_sql(G3))
def weight_spatial_g3(spark: SparkSession, d: str) -> DataFrame:
    return rounded(weights.spatial_tfidf(tables.baskets(spark, d)), "w")


@add(spatial_sql(G4))
def weight_spatial_g4(spark, d):
    return rounded(weights.spatial_tfidf(tables.shipments(spark, d)), "w")


@add(visit_sql(G3))
def weight_visit_g3(spark, d):
    return rounded(weights.visit_tfidf(tables.baskets(spark, d)), "w")


@add(spatial_sql(G3.replace("max(p_size)::DOUBLE", "1.0::DOUBLE")))
def weight_without_length_g3(spark, d):
    """Ablation: plain tf-idf."""
    return rounded(weights.spatial_tfidf(tables.baskets(spark, d), use_length=False), "w")


@add(f"WITH e AS ({G3}) SELECT t AS v, s AS f, round(n * length / sum(n * length) OVER (PARTITION BY t), 6) AS w FROM e")
def weight_without_idf_g3(spark, d):
    """Ablation: distance shares alone."""
    return rounded(weights.spatial_tfidf(tables.baskets(spark, d), use_idf=False), "w")


def cosine_sql(weighted: str, least: float = 0.0) -> str:
    return f"""WITH w AS ({weighted}), n AS (SELECT v, sqrt(sum(w * w)) AS norm FROM w GROUP BY v)
SELECT a, b, round(omega, 5) AS omega FROM (SELECT x.v AS a, y.v AS b, sum(x.w * y.w) / any_value(p.norm * q.norm) AS omega FROM w x JOIN w y ON x.f = y.f AND x.v < y.v
JOIN n p ON p.v = x.v JOIN n q ON q.v = y.v GROUP BY 1, 2) WHERE omega > {least}"""


def raw_weights(sql: str) -> str:
    """The weights without rounding."""
    return sql.replace("round(", "(").replace(", 6) AS w", ") AS w")


@add(cosine_sql(raw_weights(spatial_sql(_G5))))
def cosine_t_g5(spark, d):
    """Similarity of trips by the cells they passed."""
    return rounded(similarity.project(tables.session_cells(spark, d), side="t").drop("common"), "omega", to=5)


@add(cosine_sql(raw_weights(visit_sql(_G5))))
def cosine_s_g5(spark, d):
    """Similarity of cells by the trips that passed them."""
    return rounded(similarity.project(tables.session_cells(spark, d), side="s").drop("common"), "omega", to=5)


@add(cosine_sql(raw_weights(visit_sql(G4))))
def cosine_s_g4(spark, d):
    """Similarity of suppliers by their orders."""
    return rounded(similarity.project(tables.shipments(spark, d), side="s").drop("common"), "omega", to=5)


@add(
    cosine_sql(
        raw_weights(visit_sql(r"""SELECT page_id AS t, href AS s, count(*) AS n FROM (SELECT page_id, unnest(regexp_extract_all(html, 'href="([^"]*)"', 1)) AS href FROM pages) GROUP BY 1, 2"""))
    ).replace("SELECT a, b, round(omega, 5) AS omega", "SELECT count(*) AS edges, round(sum(omega), 3) AS total")
)
def cosine_s_g6(spark, d):
    """Similarity of link targets by the pages that have them, as counts and total."""
    own = tables.links(spark, d)
    edges = similarity.project(BipartiteGraph(own.traversal.withColumn("length", F.lit(1.0))), side="s")
    return edges.agg(F.count(F.lit(1)).alias("edges"), F.round(F.sum("omega"), 3).alias("total"))


@add(cosine_sql(raw_weights(spatial_sql(_G5)), 0.6).replace("omega > 0.6", "round(omega, 5) >= 0.6"))
def cosine_pruned_g5(spark, d):
    """The same with a least similarity, below which no pair leaves the task that adds it up."""
    weighted = weights.spatial_tfidf(tables.session_cells(spark, d), normalise=False)
    return rounded(similarity.cosine_pairs(weighted, min_sim=0.599995).drop("common"), "omega", to=5)


@add(f"WITH e AS ({G4}) SELECT x.s AS a, y.s AS b, count(*) AS common FROM e x JOIN e y ON x.t = y.t AND x.s < y.s GROUP BY 1, 2")
def common_count_g4(spark, d):
    return similarity.project(tables.shipments(spark, d), side="s", weight="common").select("a", "b", "common")


@add(f"WITH e AS ({_G5}) SELECT x.t AS a, y.t AS b, count(*) AS common FROM e x JOIN e y ON x.s = y.s AND x.t < y.t GROUP BY 1, 2")
def common_count_g5(spark, d):
    return similarity.project(tables.session_cells(spark, d), side="t", weight="common").select("a", "b", "common")



@add()
def minhash_candidates_g3(spark, d):
    """Share of the pairs of similar baskets that sampled minima find as candidates."""
    graph = BipartiteGraph(materialise(tables.baskets(spark, d).traversal, "baskets"))
    exact = materialise(similarity.cosine_pairs(weights.spatial_tfidf(graph), min_sim=0.15), "similar")
    candidates = similarity.minhash_candidates(graph, bands=48, rows=1)
    met = key_join(candidates, exact.select("a", "b", F.lit(1).alias("similar")), ["a", "b"], "left")
    return exact.agg(F.count(F.lit(1)).alias("pairs")).crossJoin(met.agg(F.count("similar").alias("found"), F.count(F.lit(1)).alias("candidates")))



# planted routes


def planted_graph(spark, d, **options):
    graph, labels, paths = tables.planted(spark, d, **options)
    return BipartiteGraph(materialise(graph.traversal, "planted")), materialise(labels, "planted-labels"), paths


#: Directed segments that leave a vertex: streets along its row, and arterials along every ninth column from the fifth.
_DEGREES = """lat AS (SELECT v, (v // 80 // 16) * 5 + v % 80 // 16 AS zone, CASE WHEN v % 80 IN (0, 79) THEN 1 ELSE 2 END AS streets, CASE WHEN v % 80 % 9 <> 4 THEN 0 WHEN v // 80 IN (0, 79) THEN 1 ELSE 2 END AS arterials
  FROM (SELECT unnest(range(6400)) AS v))"""


@add(f"""WITH {_DEGREES}, dep AS (SELECT c_nationkey AS zone, count(*) AS orders FROM orders JOIN customer ON o_custkey = c_custkey GROUP BY 1)
SELECT count(*) AS vertices, sum(streets + arterials)::BIGINT AS segments, count(DISTINCT zone) AS zones, (SELECT sum(orders) FROM dep)::BIGINT AS orders FROM lat JOIN dep USING (zone)""")
def lattice_counts(spark, d):
    """The lattice in the zones that orders leave from, which are the nations of their customers."""
    people = table(spark, d, "customer").select("c_custkey", F.col("c_nationkey").alias("zone"))
    orders = table(spark, d, "orders").select("o_custkey").join(people, F.col("o_custkey") == F.col("c_custkey"))
    # One row a zone.
    leaving = materialise(orders.groupBy("zone").agg(F.count(F.lit(1)).alias("orders")), "leaving")
    own = network.vertices(spark).join(F.broadcast(leaving.select("zone")), "zone")
    counted = own.agg(F.count(F.lit(1)).alias("vertices"), F.count_distinct("zone").alias("zones"))
    out = network.segments(spark).join(own.select(F.col("v").alias("src")), "src").agg(F.count(F.lit(1)).alias("segments"))
    return counted.crossJoin(out).crossJoin(leaving.agg(F.sum("orders").alias("orders"))).select("vertices", "segments", "zones", "orders")


@add(f"WITH {_DEGREES}, starts AS (SELECT (o_custkey * 7919 + 13) % 6400 AS v, count(*) AS orders FROM orders GROUP BY 1) SELECT sum(streets + arterials)::BIGINT AS segments, sum(arterials)::BIGINT AS arterials, sum(orders * (streets + arterials))::BIGINT AS choices FROM lat JOIN starts USING (v)")
def source_roadgrid(spark, d):
    """The lattice through the custom data source: segments that leave a vertex where orders start, and the choices of all orders."""
    from ..sources.roadgrid import register

    register(spark)
    starts = network.all_pairs(table(spark, d, "orders")).groupBy("src").agg(F.count(F.lit(1)).alias("orders"))
    own = spark.read.format("roadgrid").option("side", "80").load().join(starts, "src")
    return own.agg(F.count(F.lit(1)).alias("segments"), F.count_if(F.col("length") == 200).alias("arterials"), F.sum("orders").alias("choices"))


def pairs_sql(span: int, classes=network.CLASSES) -> str:
    rows = ", ".join(f"('{c.klass}', {c.departure}, {c.arrival}, {c.first}, {c.last})" for c in classes)
    k, off = span * span, (16 - span) // 2
    point = lambda z, x: f"(({z} // 5) * 16 + {off} + ({x}) // {span}) * 80 + ({z} % 5) * 16 + {off} + ({x}) % {span}"
    return f"""SELECT o_orderkey AS t, klass, {point('dep', f'o_custkey % {k}')} AS src, {point('arr', f'(o_orderkey * 31 + 7) % {k}')} AS dst
FROM (SELECT o_orderkey, o_custkey, c_nationkey AS dep, row_number() OVER (PARTITION BY c_nationkey ORDER BY o_orderkey) AS rank FROM orders JOIN customer ON o_custkey = c_custkey)
JOIN (VALUES {rows}) AS c(klass, dep, arr, first, last) USING (dep) WHERE rank BETWEEN first AND last"""


@add(pairs_sql(2))
def planted_pairs_span2(spark, d):
    return network.planted_pairs(table(spark, d, "orders"), table(spark, d, "customer"))


@add(pairs_sql(16))
def planted_pairs_span16(spark, d):
    return network.planted_pairs(table(spark, d, "orders"), table(spark, d, "customer"), span=16)


def _cost_sql(pairs: str) -> str:
    """An optimal route keeps to one arterial: the least over the nine of them."""
    return f"""WITH p AS ({pairs}), x AS (SELECT t, src // 80 AS i1, src % 80 AS j1, dst // 80 AS i2, dst % 80 AS j2 FROM p)
SELECT t, min(CASE WHEN i1 = i2 THEN 3 * abs(j1 - j2) ELSE 3 * (abs(j1 - a) + abs(a - j2)) + (1 + (a // 9) % 2) * abs(i1 - i2) END)::BIGINT AS cost
FROM x CROSS JOIN (SELECT unnest(range(4, 80, 9)) AS a) GROUP BY t"""


@add(_cost_sql(pairs_sql(2)))
def planted_cost_closed_form(spark, d):
    """Travel time of the planted routes."""
    _, _, paths = tables.planted(spark, d)
    return routing.costs(network.segments(spark), paths).select("t", "cost")


@add(_cost_sql(pairs_sql(16)))
def planted_cost_span16(spark, d):
    _, _, paths = tables.planted(spark, d, span=16)
    return routing.costs(network.segments(spark), paths).select("t", "cost")



# route A


def _side(spark, d, side: str = "t", **options) -> tuple[BipartiteGraph, DataFrame, DataFrame]:
    graph, labels, _ = planted_graph(spark, d, **options)
    return graph, labels, materialise(similarity.project(graph, side=side), "projected")


def _report(labels: DataFrame, part: DataFrame, **more) -> DataFrame:
    found = agreement.confusion(labels, part)
    out = agreement.ari(found).crossJoin(agreement.purity(found))
    return rounded(out.withColumns({k: F.lit(v) for k, v in more.items()}), "ari", "purity")


def _compared(graph: BipartiteGraph, labels: DataFrame, membership: DataFrame, **more) -> DataFrame:
    """Agreement of either route with the classes, of the first at both levels."""
    out = _report(labels, hierarchy.cut(membership, level=1), route="modularity 1", **more)
    out = out.unionByName(_report(labels, hierarchy.cut(membership, level=2), route="modularity 2", **more))
    model = cocluster.fit(graph, restarts=2)
    return out.unionByName(_report(labels, model.row_part.select(F.col("t").alias("v"), F.col("ct").alias("c")), route="co-clustering", **more))


def _both_routes(spark, d, **options) -> DataFrame:
    graph, labels, edges = _side(spark, d, **options)
    return _compared(graph, labels, hierarchy.nested(edges))


@add()
def communities_g1(spark, d):
    _, labels, edges = _side(spark, d)
    part = materialise(modularity.communities(edges), "communities")
    return _report(labels, part).crossJoin(rounded(modularity.score(edges, part), "modularity"))


@add()
def communities_segments_g1(spark, d):
    _, _, edges = _side(spark, d, side="s")
    part = materialise(modularity.communities(edges), "communities")
    return part.groupBy("c").agg(F.count(F.lit(1)).alias("segments"))


@add()
def communities_distributed_g1(spark, d):
    """The same by rounds of joins, the kernel only for what is left."""
    _, labels, edges = _side(spark, d)
    part = materialise(modularity.communities(edges, mode="distributed", local_edges=200), "communities")
    return _report(labels, part).crossJoin(rounded(modularity.score(edges, part), "modularity"))


@add()
def nested_g1(spark, d):
    _, _, edges = _side(spark, d)
    return hierarchy.nested(edges, max_depth=3)


@add()
def nested_null_gate_g1(spark, d):
    """Refined only where that beats the same weights at random places."""
    _, labels, edges = _side(spark, d)
    membership = hierarchy.nested(edges, gate="null_model")
    return _report(labels, hierarchy.cut(membership, level=2))


@add()
def refine_one_cluster_g1(spark, d):
    _, _, edges = _side(spark, d)
    membership = hierarchy.nested(edges, max_depth=1)
    largest = membership.groupBy("cluster").count().orderBy(F.desc("count"), "cluster").first()["cluster"]
    return hierarchy.refine(edges, membership, largest)


@add()
def recovery_g1(spark, d):
    """What became of each class at the second level."""
    _, labels, edges = _side(spark, d)
    return agreement.recovery(agreement.confusion(labels, hierarchy.cut(hierarchy.nested(edges), level=2)))


@add()
def confusion_g1(spark, d):
    _, labels, edges = _side(spark, d)
    return rounded(agreement.confusion(labels, hierarchy.cut(hierarchy.nested(edges), level=2)), "ratio")


@add()
def ari_both_routes_span2(spark, d):
    return _both_routes(spark, d)


@add()
def ari_both_routes_span4(spark, d):
    return _both_routes(spark, d, span=4)


@add()
def ari_both_routes_span8(spark, d):
    return _both_routes(spark, d, span=8)


@add()
def ari_both_routes_span16(spark, d):
    return _both_routes(spark, d, span=16)


@add()
def ari_vertex_ties_g1(spark, d):
    """Both routes by span where equally fast routes go by smaller vertices: what the rule for ties changes."""
    out = None
    for span in (2, 4, 8, 16):
        graph, labels, edges = _side(spark, d, span=span, ties="vertex")
        one = _compared(graph, labels, hierarchy.nested(edges), span=span)
        out = one if out is None else out.unionByName(one)
    return out


@add()
def interactions_g1(spark, d):
    """Two classes under each kind of interaction: how well the first level tells them apart."""
    out = None
    for kind in ("none", "diverge", "converge", "inverse"):
        _, labels, edges = _side(spark, d, classes=network.interacting(kind))
        one = _report(labels, modularity.communities(edges), interaction=kind)
        out = one if out is None else out.unionByName(one)
    return out


@add()
def noise_curve_g1(spark, d):
    """Agreement of both routes as more trajectories end at random places."""
    out = None
    for percent in (0, 10, 30):
        graph, labels, edges = _side(spark, d, noise=percent)
        one = _compared(graph, labels, hierarchy.nested(edges), noise=percent)
        out = one if out is None else out.unionByName(one)
    return out


def _page_links(spark, d) -> tuple[BipartiteGraph, DataFrame]:
    """Pages by what they link to, and the language in their URL."""
    graph = BipartiteGraph(materialise(tables.links(spark, d).traversal, "links"))
    labels = table(spark, d, "pages").select(F.col("page_id").alias("v"), F.regexp_extract("url", "^[a-z]+://[^/]+/([a-z]{2})/", 1).alias("klass"))
    return graph, labels


@add()
def ari_both_routes_g6(spark, d):
    """Pages against the language of their URL."""
    graph, labels = _page_links(spark, d)
    return _compared(graph, labels, implicit.nested(similarity.vectors(graph)))


@add()
def ari_both_routes_g7(spark, d):
    """Control: vectors whose labels can't be told apart by their dimensions."""
    graph = BipartiteGraph(materialise(tables.vectors(spark, d).traversal, "vectors"))
    labels = table(spark, d, "embeddings").select(F.col("vec_id").alias("v"), F.col("label").cast("string").alias("klass"))
    return _compared(graph, labels, implicit.nested(similarity.vectors(graph)))


@add()
def crossed_g6(spark, d):
    """Clusters of pages and of link targets, found apart and read together."""
    graph, _ = _page_links(spark, d)
    rows = implicit.communities(similarity.vectors(graph)).select(F.col("v").alias("t"), F.col("c").alias("ct"))
    columns = implicit.communities(similarity.vectors(graph, side="s")).select(F.col("v").alias("s"), F.col("c").alias("cs"))
    return mutual.contributions(mutual.crossed(graph, rows, columns))


@add()
def cut_k_g1(spark, d):
    """The finest level with at most eight clusters."""
    _, labels, edges = _side(spark, d)
    return _report(labels, hierarchy.cut(hierarchy.nested(edges, max_depth=3), k=8))


@add()
def scaling_curve_g1(spark, d):
    """Work of either route as the routes spread over more segments: edges, pairs of the projection, merges and pairs of clusters looked at."""
    out = None
    for span in (2, 4, 8):
        graph, _, edges = _side(spark, d, span=span)
        trace = cocluster.fit(graph, restarts=0).trace.where("step = 'merge'").agg(F.count(F.lit(1)).alias("merges"), F.sum("pairs").alias("pairs_evaluated"))
        one = graph.stats().crossJoin(edges.agg(F.count(F.lit(1)).alias("projection_pairs"))).crossJoin(trace).withColumn("span", F.lit(span))
        out = one if out is None else out.unionByName(one)
    return out


@add()
def spectral_g1(spark, d):
    _, labels, edges = _side(spark, d)
    return _report(labels, rivals.spectral(edges, 5))


@add()
def euclid_g1(spark, d):
    """k-means on endpoints, blind to the network."""
    pairs = network.planted_pairs(table(spark, d, "orders"), table(spark, d, "customer"))
    ends = pairs.select(F.col("t").alias("v"), "klass", *[(F.floor(F.col(c) / 80) if k == "row" else F.col(c) % 80).cast("double").alias(f"{c}_{k}") for c in ("src", "dst") for k in ("row", "col")])
    part = rivals.euclidean(ends, 5, features=["src_row", "src_col", "dst_row", "dst_col"])
    return _report(pairs.select(F.col("t").alias("v"), "klass"), part)


@add()
def common_count_communities_g1(spark, d):
    """Rival weights: communities on plain counts of shared segments."""
    graph, labels, _ = planted_graph(spark, d)
    return _report(labels, modularity.communities(similarity.project(graph, weight="common")))


@add()
def without_length_communities_g1(spark, d):
    graph, labels, _ = planted_graph(spark, d)
    return _report(labels, modularity.communities(similarity.cosine_pairs(weights.spatial_tfidf(graph, use_length=False))))


@add()
def without_idf_communities_g1(spark, d):
    graph, labels, _ = planted_graph(spark, d)
    return _report(labels, modularity.communities(similarity.cosine_pairs(weights.spatial_tfidf(graph, use_idf=False))))


@add()
def trajectory_only_g6(spark, d):
    """Pages by what they link to, against the language in their URL."""
    graph = tables.links(spark, d)
    labels = table(spark, d, "pages").select(F.col("page_id").alias("v"), F.regexp_extract("url", "^[a-z]+://[^/]+/([a-z]{2})/", 1).alias("klass"))
    return _report(labels, implicit.communities(similarity.vectors(graph)))


@add()
def negative_control_g7(spark, d):
    """Vectors without structure: agreement with their labels is about none."""
    graph = tables.vectors(spark, d)
    labels = table(spark, d, "embeddings").select(F.col("vec_id").alias("v"), F.col("label").cast("string").alias("klass"))
    return _report(labels, implicit.communities(similarity.vectors(graph)))


# route B


def _fit_g1(spark, d, **options) -> tuple[cocluster.CoClustering, DataFrame]:
    graph, labels, _ = planted_graph(spark, d)
    return cocluster.fit(graph, **options), labels


@add()
def cocluster_g1(spark, d):
    return _fit_g1(spark, d, restarts=2)[0].block


@add()
def compression_g1(spark, d):
    return rounded(_fit_g1(spark, d, restarts=2)[0].compression(), "cost", "null_cost", "compression", to=4)


@add()
def exchange_trace(spark, d):
    """Ablation of the search: merges alone, with exchanges, with restarts."""
    graph, labels, _ = planted_graph(spark, d)
    out = None
    for name, options in (("merges", {"refine": False, "restarts": 0}), ("exchanges", {"restarts": 0}), ("restarts", {"restarts": 3}), ("first rise", {"refine": False, "restarts": 0, "stop": "first_rise"})):
        model = cocluster.fit(graph, **options)
        one = rounded(model.cost(), "total", to=4).select("total").crossJoin(_report(labels, model.row_part.select(F.col("t").alias("v"), F.col("ct").alias("c")), search=name))
        out = one if out is None else out.unionByName(one)
    return out


@add()
def merge_trace_g1(spark, d):
    return _fit_g1(spark, d, restarts=0)[0].trace


@add()
def vns_trace(spark, d):
    """Independent restarts, a task each."""
    graph, _, _ = planted_graph(spark, d)
    return rounded(cocluster.search(spark, graph, restarts=4), "cost", to=4)


@add()
def coarsened_g1(spark, d):
    model, labels = _fit_g1(spark, d, restarts=0)
    part = cocluster.coarsen(model, 5, 5)
    return _report(labels, part.where("side = 't'").select("v", "c"))


@add()
def distributed_fit_g1(spark, d):
    """The route for large graphs: hashed start, exchanges by joins, merges of blocks."""
    model, labels = _fit_g1(spark, d, restarts=0, local_cells=100, start=40, passes=2)
    return _report(labels, model.row_part.select(F.col("t").alias("v"), F.col("ct").alias("c"))).crossJoin(model.compression())


@add()
def cocluster_g2(spark, d):
    """Documents by their words against their language, through the route for large graphs."""
    graph = BipartiteGraph.of(tables.word_rows(spark, d), t="doc_id", s=F.xxhash64("word"), length=None)
    model = cocluster.fit(graph, restarts=0)
    labels = table(spark, d, "documents").select(F.col("doc_id").alias("v"), F.col("lang").alias("klass"))
    return _report(labels, model.row_part.select(F.col("t").alias("v"), F.col("ct").alias("c"))).crossJoin(model.compression())



@add()
def alternate_g8(spark, d):
    graph = tables.flows(spark, d)
    rows, columns = cocluster.alternate(graph, 3, 3)
    return mutual.contributions(mutual.crossed(graph, rows, columns))



@add()
def assign_new_g1(spark, d):
    """Trajectories that were held out go to the cluster of their like."""
    graph, labels, _ = planted_graph(spark, d)
    held = F.col("t") % 5 == 0
    model = cocluster.fit(BipartiteGraph(graph.traversal.where(~held)), restarts=0)
    given = cocluster.assign(model, BipartiteGraph(graph.traversal.where(held)))
    return _report(labels, given.select(F.col("t").alias("v"), F.col("ct").alias("c")))


# blocks, roles, measures


@add()
def roles_g1(spark, d):
    return mutual.roles(_fit_g1(spark, d, restarts=1)[0].block)


@add()
def reordered_g1(spark, d):
    model, _ = _fit_g1(spark, d, restarts=1)
    return mutual.reordered(model.graph, model.row_part, model.col_part)


@add()
def crossed_homogeneity_g1(spark, d):
    """Mean dispersion inside blocks, of either route: co-clustering's blocks are the more even."""
    graph, _, _ = planted_graph(spark, d)
    model = cocluster.fit(graph, restarts=1)
    a_rows = modularity.communities(similarity.project(graph, side="t")).select(F.col("v").alias("t"), F.col("c").alias("ct"))
    a_columns = modularity.communities(similarity.project(graph, side="s")).select(F.col("v").alias("s"), F.col("c").alias("cs"))
    of = lambda rows, columns, route: mutual.profile(graph, rows, columns).agg((F.sum(F.col("dispersion") * F.col("edges")) / F.sum("edges")).alias("dispersion")).withColumn("route", F.lit(route))
    return of(a_rows, a_columns, "modularity").unionByName(of(model.row_part, model.col_part, "co-clustering"))


@add()
def mi_blocks_g1(spark, d):
    return mutual.contributions(_fit_g1(spark, d, restarts=1)[0].block)


_REGIONS = "SELECT n_nationkey::BIGINT AS n, n_regionkey::BIGINT AS r FROM nation"
_OD_BLOCK = f"WITH g AS ({G8}), reg AS ({_REGIONS}), block AS (SELECT a.r AS ct, b.r AS cs, sum(g.n)::BIGINT AS m, count(*) AS edges FROM g JOIN reg a ON g.t = a.n JOIN reg b ON g.s = b.n GROUP BY 1, 2)"


def _regions(spark, d) -> tuple[BipartiteGraph, DataFrame, DataFrame]:
    graph = tables.flows(spark, d)
    region = table(spark, d, "nation").select(F.col("n_nationkey").cast("long").alias("t"), F.col("n_regionkey").cast("long").alias("ct"))
    return graph, region, region.select(F.col("t").alias("s"), F.col("ct").alias("cs"))


@add(_OD_BLOCK + " SELECT ct, cs, m, round(m / sum(m) OVER (), 6) AS p FROM block")
def block_frequency_g8(spark, d):
    parts = mutual.contributions(mutual.crossed(*_regions(spark, d)))
    return rounded(parts.select("ct", "cs", "m", "p"), "p")


@add(
    _OD_BLOCK
    + """, p AS (SELECT ct, cs, m / sum(m) OVER () AS p, sum(m) OVER (PARTITION BY ct) / sum(m) OVER () AS pt, sum(m) OVER (PARTITION BY cs) / sum(m) OVER () AS ps FROM block)
SELECT ct, cs, round(pt * ps, 6) AS expected, round(p * ln(p / (pt * ps)), 6) AS mi FROM p"""
)
def mi_nation_od(spark, d):
    parts = mutual.contributions(mutual.crossed(*_regions(spark, d)))
    return rounded(parts.select("ct", "cs", "expected", "mi"), "expected", "mi")


@add(
    _OD_BLOCK
    + """, sizes AS (SELECT r, count(*) AS n FROM reg WHERE n IN (SELECT t FROM g) GROUP BY 1), cols AS (SELECT r, count(*) AS n FROM reg WHERE n IN (SELECT s FROM g) GROUP BY 1)
SELECT ct, cs, edges, round(edges::DOUBLE / (sizes.n * cols.n), 6) AS density FROM block JOIN sizes ON ct = sizes.r JOIN cols ON cs = cols.r"""
)
def block_density_region(spark, d):
    graph, rows, columns = _regions(spark, d)
    rows = rows.join(graph.traversal.select("t").distinct(), "t", "left_semi")
    columns = columns.join(graph.traversal.select("s").distinct(), "s", "left_semi")
    return rounded(mutual.profile(graph, rows, columns).select("ct", "cs", "edges", "density"), "density")


def log_partitions_sql(n: str, k: str) -> str:
    """ln of the partitions of n things into at most k classes, by inclusion and exclusion; powers are taken of shares of k, or they would overflow."""
    return f"""(SELECT ln(sum(st)) + any_value({n}) * ln(any_value({k})) FROM (SELECT j, sum(CASE WHEN (j - i) % 2 = 0 THEN 1 ELSE -1 END * exp(lgamma(j + 1) - lgamma(i + 1) - lgamma(j - i + 1)) * pow(i::DOUBLE / {k}, {n}) / exp(lgamma(j + 1))) AS st
FROM (SELECT unnest(range(1, {k} + 1)) AS j), (SELECT unnest(range(1, {k} + 1)) AS i) WHERE i <= j GROUP BY j))"""


@add(
    _OD_BLOCK
    + f""", tv AS (SELECT t AS v, sum(n) AS n FROM g GROUP BY 1), sv AS (SELECT s AS v, sum(n) AS n FROM g GROUP BY 1),
tc AS (SELECT r, count(*) AS size, sum(tv.n) AS m, sum(lgamma(tv.n + 1)) AS own FROM tv JOIN reg ON v = reg.n GROUP BY 1),
sc AS (SELECT r, count(*) AS size, sum(sv.n) AS m, sum(lgamma(sv.n + 1)) AS own FROM sv JOIN reg ON v = reg.n GROUP BY 1),
one AS (SELECT (SELECT sum(m) FROM block) AS m, (SELECT count(*) FROM tv) AS nt, (SELECT count(*) FROM sv) AS ns, (SELECT count(*) FROM tc) AS kt, (SELECT count(*) FROM sc) AS ks)
SELECT round(ln(nt) + ln(ns) + {log_partitions_sql('(SELECT count(*) FROM tv)', '(SELECT count(*) FROM tc)')} + {log_partitions_sql('(SELECT count(*) FROM sv)', '(SELECT count(*) FROM sc)')}
+ lgamma(m + kt * ks) - lgamma(kt * ks) - lgamma(m + 1)
+ (SELECT sum(lgamma(m + size) - lgamma(size) - lgamma(m + 1)) FROM tc) + (SELECT sum(lgamma(m + size) - lgamma(size) - lgamma(m + 1)) FROM sc)
+ lgamma(m + 1) - (SELECT sum(lgamma(m + 1)) FROM block) + (SELECT sum(lgamma(m + 1) - own) FROM tc) + (SELECT sum(lgamma(m + 1) - own) FROM sc), 3) AS total FROM one"""
)
def map_cost_g8_region(spark, d):
    """Code length of the regions as clusters."""
    return rounded(criterion.cost(*_regions(spark, d)).select("total"), "total", to=3)



@add(
    """WITH c AS (SELECT lang AS klass, source AS cluster, count(*) AS n FROM documents GROUP BY 1, 2), r AS (SELECT sum(n) AS n FROM c GROUP BY klass), k AS (SELECT sum(n) AS n FROM c GROUP BY cluster),
x AS (SELECT (SELECT sum(n * (n - 1) / 2.0) FROM c) AS b, (SELECT sum(n * (n - 1) / 2.0) FROM r) AS r, (SELECT sum(n * (n - 1) / 2.0) FROM k) AS k, (SELECT sum(n) FROM c) AS t)
SELECT round((b - r * k / (t * (t - 1) / 2.0)) / ((r + k) / 2.0 - r * k / (t * (t - 1) / 2.0)), 6) AS ari FROM x"""
)
def ari_lang_vs_source(spark, d):
    docs = table(spark, d, "documents").select(F.col("doc_id").alias("v"), F.col("lang").alias("klass"), F.col("source").alias("c"))
    return rounded(agreement.ari(agreement.confusion(docs.select("v", "klass"), docs.select("v", "c"))), "ari")


_URL_LANG = "regexp_extract(url, '^[a-z]+://[^/]+/([a-z]{2})/', 1)"
_HTML_LANG = "regexp_extract(html, '<html lang=\"([a-z]+)\"', 1)"


def _page_parts(spark, d) -> tuple[DataFrame, DataFrame]:
    own = table(spark, d, "pages").select(F.col("page_id").alias("v"), F.regexp_extract("url", "^[a-z]+://[^/]+/([a-z]{2})/", 1).alias("klass"), F.regexp_extract("html", '<html lang="([a-z]+)"', 1).alias("c"))
    return own.select("v", "klass"), own.select("v", "c")


@add(f"SELECT klass, cluster, n, round(n / sum(n) OVER (PARTITION BY klass), 6) AS ratio FROM (SELECT {_URL_LANG} AS klass, {_HTML_LANG} AS cluster, count(*) AS n FROM pages GROUP BY 1, 2)")
def confusion_g6(spark, d):
    return rounded(agreement.confusion(*_page_parts(spark, d)), "ratio")


@add(f"WITH c AS (SELECT {_URL_LANG} AS klass, {_HTML_LANG} AS cluster, count(*) AS n FROM pages GROUP BY 1, 2), m AS (SELECT max(n) AS main, sum(n) AS n FROM c GROUP BY cluster) SELECT round(sum(main) / sum(n), 6) AS purity, sum(main) = sum(n) AS all_pure, count(*) AS clusters FROM m")
def purity_g6(spark, d):
    return rounded(agreement.purity(agreement.confusion(*_page_parts(spark, d))), "purity")


@add(
    f"""WITH e AS (SELECT least(t, s) AS a, greatest(t, s) AS b, sum(n)::DOUBLE AS w FROM ({G8}) WHERE t <> s GROUP BY 1, 2), reg AS ({_REGIONS}),
x AS (SELECT w, p.r AS ca, q.r AS cb FROM e JOIN reg p ON a = p.n JOIN reg q ON b = q.n), k AS (SELECT c, sum(w) AS k FROM (SELECT ca AS c, w FROM x UNION ALL SELECT cb, w FROM x) GROUP BY c)
SELECT round((SELECT sum(CASE WHEN ca = cb THEN w ELSE 0 END) / sum(w) FROM x) - (SELECT sum(k * k) FROM k) / (4 * pow((SELECT sum(w) FROM x), 2)), 6) AS modularity"""
)
def modularity_region_partition(spark, d):
    graph, region, _ = _regions(spark, d)
    own = graph.traversal.where("t <> s").groupBy(F.least("t", "s").alias("a"), F.greatest("t", "s").alias("b")).agg(F.sum("n").cast("double").alias("omega"))
    return rounded(modularity.score(own, region.select(F.col("t").alias("v"), F.col("ct").alias("c"))), "modularity")


#: Of each published value the ranks at which a planted class is cut: parts of class 1, and of class 3.
_SPLITS = {"first": {"1": (3, 6), "3": (10,)}, "second": {"1": (3, 7), "3": (8,)}, "third": {"1": (5,), "3": (10,)}}


def _golden_ari_sql() -> str:
    def one(cuts: dict[str, tuple[int, ...]]) -> str:
        part = " ".join(f"WHEN klass = '{k}' THEN {' + '.join(f'(rank > {x})::INT' for x in at)}" for k, at in cuts.items())
        two = lambda n: f"sum({n} * ({n} - 1) / 2)"
        return f"""(WITH cells AS (SELECT klass, CASE {part} ELSE 0 END AS part, count(*) AS n FROM ranked GROUP BY 1, 2),
x AS (SELECT (SELECT {two('n')} FROM cells) AS joint, (SELECT {two('n')} FROM (SELECT sum(n) AS n FROM cells GROUP BY klass)) AS a, (SELECT {two('n')} FROM cells) AS b, (SELECT {two('n')} FROM (SELECT sum(n) AS n FROM cells)) AS pairs)
SELECT round((joint - a * b / pairs) / ((a + b) / 2 - a * b / pairs), 3) FROM x)"""

    return f"WITH ranked AS (SELECT klass, row_number() OVER (PARTITION BY klass ORDER BY t) AS rank FROM ({pairs_sql(2)})) SELECT {', '.join(f'{one(cuts)} AS {name}' for name, cuts in _SPLITS.items())}"


@add(_golden_ari_sql())
def golden_ari_849(spark, d):
    """The published values from splits of the planted classes that give them: every part is a cluster of its own."""
    pairs = network.planted_pairs(table(spark, d, "orders"), table(spark, d, "customer"))
    ranked = materialise(pairs.select("klass", F.row_number().over(Window.partitionBy("klass").orderBy("t")).alias("rank")), "ranked")
    out = None
    for name, cuts in _SPLITS.items():
        part = F.lit(0)
        for klass, at in cuts.items():
            part = F.when(F.col("klass") == klass, sum((F.col("rank") > x).cast("int") for x in at)).otherwise(part)
        cells = ranked.groupBy("klass", (F.col("klass").cast("int") * 10 + part).alias("cluster")).agg(F.count(F.lit(1)).alias("n"))
        one = agreement.ari(cells).select(F.round("ari", 3).alias(name))
        out = one if out is None else out.crossJoin(one)
    return out


@add(
    """WITH b AS (SELECT CASE WHEN o_orderkey % 1000 < 216 THEN 0 ELSE 1 END AS ct, CASE WHEN o_orderkey % 1000 < 173 THEN 0 ELSE 1 END AS cs, count(*) AS m FROM orders GROUP BY 1, 2),
x AS (SELECT ct, cs, m / sum(m) OVER () AS p, sum(m) OVER (PARTITION BY ct) / sum(m) OVER () AS pt, sum(m) OVER (PARTITION BY cs) / sum(m) OVER () AS ps FROM b)
SELECT round(pt * ps, 6) AS expected, round(p * ln(p / (pt * ps)), 6) AS mi FROM x WHERE ct = 0 AND cs = 0"""
)
def golden_block(spark, d):
    """The published example block, 21.6 % by 17.3 % with 17.3 % of the visits, as orders dealt out in these shares by their keys."""
    key = F.col("o_orderkey") % 1000
    dealt = table(spark, d, "orders").select(F.when(key < 216, 0).otherwise(1).cast("long").alias("ct"), F.when(key < 173, 0).otherwise(1).cast("long").alias("cs"))
    own = dealt.groupBy("ct", "cs").agg(F.count(F.lit(1)).alias("m"))
    return rounded(mutual.contributions(own).where("ct = 0 and cs = 0").select("expected", "mi"), "expected", "mi")


# trips and map matching


@add("WITH g AS (SELECT user_id, ts, event_id, CASE WHEN ts - lag(ts) OVER w > INTERVAL 24 HOUR OR lag(ts) OVER w IS NULL THEN 1 ELSE 0 END AS new FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)) SELECT event_id, (sum(new) OVER (PARTITION BY user_id ORDER BY ts, event_id) - 1)::BIGINT AS trip FROM g")
def trips_by_gap(spark, d):
    return tables.sessions(spark, d).select("event_id", "trip")


@add(_G5)
def edges_g5_cells(spark, d):
    return tables.session_cells(spark, d).traversal


def _points(spark, d) -> tuple[DataFrame, DataFrame]:
    """Events as points near the streets of a 10 by 10 lattice, and those streets."""
    own = tables.sessions(spark, d)
    jitter = lambda m: (F.pmod(F.col("event_id") * m, F.lit(100)) - 50) / 200.0
    points = own.select("t", F.col("event_id").cast("int").alias("pos"), (F.col("k") % 10 + jitter(7919)).alias("x"), (F.floor(F.col("k") / 10) + jitter(104729)).alias("y"))
    streets = network.segments(spark, side=10, first=0, step=1)
    return points, streets.select("s", (F.col("src") % 10).cast("double").alias("x1"), F.floor(F.col("src") / 10).cast("double").alias("y1"), (F.col("dst") % 10).cast("double").alias("x2"), F.floor(F.col("dst") / 10).cast("double").alias("y2"))


@add(
    _TRIPS
    + """, p AS (SELECT user_id * 1000000 + trip AS t, event_id::INT AS pos, k % 10 + ((event_id * 7919) % 100 - 50) / 200.0::DOUBLE AS x, k // 10 + ((event_id * 104729) % 100 - 50) / 200.0::DOUBLE AS y FROM x),
i AS (SELECT unnest(range(90)) AS i), half AS (SELECT i AS s, i % 9 AS x1, i // 9 AS y1, i % 9 + 1 AS x2, i // 9 AS y2 FROM i UNION ALL SELECT 180 + (i // 9) * 18 + i % 9, i // 9, i % 9, i // 9, i % 9 + 1 FROM i),
roads AS (SELECT * FROM half UNION ALL SELECT CASE WHEN s < 180 THEN s + 90 ELSE s + 9 END, x2, y2, x1, y1 FROM half),
near AS (SELECT t, pos, s, greatest(0.0, least(1.0, (x - x1) * (x2 - x1) + (y - y1) * (y2 - y1))) AS share, x - x1 AS ox, y - y1 AS oy, x2 - x1 AS dx, y2 - y1 AS dy FROM p JOIN roads ON abs(x - (x1 + x2) / 2.0) <= 1.1 AND abs(y - (y1 + y2) / 2.0) <= 1.1),
far AS (SELECT t, pos, s, sqrt(pow(ox - share * dx, 2) + pow(oy - share * dy, 2)) AS distance FROM near)
SELECT t, pos, min(struct_pack(d := round(distance, 9), s := s)).s AS s FROM far WHERE distance <= 0.5 GROUP BY t, pos"""
)
def match_snap(spark, d):
    points, streets = _points(spark, d)
    return ingest.match_points(points, streets, radius=0.5)


@add()
def match_hmm(spark, d):
    points, streets = _points(spark, d)
    return ingest.match_points(points, streets, method="hmm", radius=0.5)


@add("SELECT count(*) AS edges, count(DISTINCT doc_id) AS trajectories, count(DISTINCT word) AS segments, sum(n)::BIGINT AS visits FROM (SELECT doc_id, word, count(*) AS n FROM (SELECT doc_id, unnest(regexp_extract_all(lower(text), '[\\p{L}]+')) AS word FROM documents) GROUP BY 1, 2)")
def graph_stats_g2(spark, d):
    return tables.words(spark, d).stats()


@add("SELECT count(*) AS edges, count(DISTINCT conv_id) AS trajectories, count(DISTINCT word) AS segments, sum(n)::BIGINT AS visits FROM (SELECT conv_id, word, count(*) AS n FROM (SELECT conv_id, unnest(regexp_extract_all(lower(text), '[\\p{L}]+')) AS word FROM conversations) GROUP BY 1, 2)")
def graph_stats_g10(spark, d):
    return tables.dialogues(spark, d).stats()


@add("SELECT count(*) AS edges, count(DISTINCT t) AS trajectories, count(DISTINCT s) AS segments, count(*)::BIGINT AS visits FROM (SELECT DISTINCT l_orderkey AS t, l_suppkey AS s FROM lineitem)")
def binarized_g4(spark, d):
    return tables.shipments(spark, d).binarize().stats()


@add()
def scaling_rounds(spark, d):
    """What each route counted on the planted routes: pairs of the projection, merges evaluated, edges."""
    graph, _, edges = _side(spark, d)
    trace = cocluster.fit(graph, restarts=0).trace.where("step = 'merge'").agg(F.count(F.lit(1)).alias("merges"), F.sum("pairs").alias("pairs_evaluated"))
    return graph.stats().crossJoin(edges.agg(F.count(F.lit(1)).alias("projection_pairs"))).crossJoin(trace)


@add(_cost_sql("SELECT o_orderkey AS t, (o_custkey * 7919 + 13) % 6400 AS src, (o_orderkey * 104729 + 7) % 6400 AS dst FROM orders") + " HAVING cost > 0")
def routes_all_orders(spark, d):
    """Larger data: a trajectory for each order, with its travel time."""
    pairs = network.all_pairs(table(spark, d, "orders"))
    return routing.costs(network.segments(spark), routing.shortest(network.segments(spark), pairs)).select("t", "cost")


@add()
def matched_merges_g1(spark, d):
    """Greedy merges by joins: all pairs of clusters that are each other's best, a round at a time."""
    graph, labels, _ = planted_graph(spark, d)
    rows, _, _ = greedy.merge(graph, criterion.finest(graph), batch="matched", max_rounds=12)
    return _report(labels, rows.select(F.col("t").alias("v"), F.col("ct").alias("c")))


@add()
def single_merges_g9(spark, d):
    """The faithful variant by joins: the best merge of a round alone, on the flows between regions."""
    graph = BipartiteGraph(mutual.crossed(*_regions(spark, d)).select(F.col("ct").alias("t"), F.col("cs").alias("s"), F.col("m").alias("n"), F.lit(1.0).alias("length")))
    return greedy.merge(graph, criterion.finest(graph), batch="single")[2]


@add()
def sampled_fit_g1(spark, d):
    """Fitted on a hashed half of the trajectories, the others assigned."""
    graph, labels, _ = planted_graph(spark, d)
    given = cocluster.fit_sampled(graph, share=0.5, restarts=0)
    return _report(labels, given.select(F.col("t").alias("v"), F.col("ct").alias("c")))



@add()
def sink_checkpoint_levels(spark, d):
    """Levels of a hierarchy written by level and read back with pruning."""
    _, _, edges = _side(spark, d)
    path = new_path(spark, "levels")
    hierarchy.nested(edges, max_depth=2).write.partitionBy("level").parquet(path)
    return spark.read.parquet(path).where("level = 2").select("v", "cluster", "parent")



@add()
def planted_random_classes(spark, d):
    """The generator with random zones and sizes: six classes and how well communities tell them apart."""
    _, labels, edges = _side(spark, d, classes=network.zone_pairs(spark, 6), span=4)
    return _report(labels, modularity.communities(edges))


@add()
def reference_costs_g1(spark, d):
    """Code length of the planted classes with the fitted columns, beside the fitted model, one block and single vertices."""
    graph, labels, _ = planted_graph(spark, d)
    model = cocluster.fit(graph, restarts=1)
    planted = labels.select(F.col("v").alias("t"), F.col("klass").cast("long").alias("ct"))
    choices = {"fitted": (model.row_part, model.col_part), "planted rows": (planted, model.col_part), "one block": criterion.null_model(graph), "finest": criterion.finest(graph)}
    out = None
    for name, parts in choices.items():
        one = criterion.cost(graph, *parts).withColumn("model", F.lit(name))
        out = one if out is None else out.unionByName(one)
    return out


@add()
def dropped_segments_g1(spark, d):
    """A fifth of the visited segments is missing from the paths: agreement of the first level."""
    _, labels, paths = tables.planted(spark, d)
    graph = BipartiteGraph.of(to_traversals(network.noisy_paths(paths, 20), network.segments(spark)))
    return _report(labels, modularity.communities(similarity.project(graph, side="t")))
