"""Queries of the core on the planted routes and on nations, each with SQL that builds its graph anew from the tables.

Routes, weights, similarities, code lengths and block measures of known
partitions are held against DuckDB in full; so are fitted models where the
outcome is known, which is one block on data without structure.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, functions as F

from ..model import BipartiteGraph
from ..operators import cocluster, criterion, modularity, mutual, network, similarity, weights
from ..scratch import materialise
from ..sources import tables
from ..sources.tables import table
from .methods import G3, G4, G8, cosine_sql, log_partitions_sql, pairs_sql, planted_graph, raw_weights, rounded, spatial_sql, visit_sql
from .registry import Catalog

catalog = Catalog()
add = catalog.add


def paths_sql(span: int = 2) -> str:
    """The planted routes in closed form: along the row, the best arterial (of equal ones the first), and the other row."""
    return f"""p AS ({pairs_sql(span)}), x AS (SELECT t, klass, src // 80 AS i1, src % 80 AS j1, dst // 80 AS i2, dst % 80 AS j2 FROM p),
choices AS (SELECT t, klass, i1, j1, i2, j2, min(struct_pack(cost := 3 * (abs(j1 - a) + abs(a - j2)) + (1 + (a // 9) % 2) * abs(i1 - i2), a := a)) AS least
  FROM x CROSS JOIN (SELECT unnest(range(4, 80, 9)) AS a) GROUP BY t, klass, i1, j1, i2, j2),
best AS (SELECT t, klass, i1, j1, i2, j2, CASE WHEN i1 = i2 THEN j1 ELSE least.a END AS a FROM choices),
paths AS (SELECT t, klass, CASE WHEN j1 < a THEN c - j1 ELSE j1 - 1 - c END AS pos, CASE WHEN j1 < a THEN 0 ELSE 6320 END + i1 * 79 + c AS s, 100 + 10 * (i1 % 7) AS length
    FROM (SELECT *, unnest(range(least(j1, a)::BIGINT, greatest(j1, a)::BIGINT)) AS c FROM best)
  UNION ALL SELECT t, klass, abs(j1 - a) + CASE WHEN i1 < i2 THEN r - i1 ELSE i1 - 1 - r END, 12640 + ((a - 4) // 9) * 158 + CASE WHEN i1 < i2 THEN 0 ELSE 79 END + r, 200
    FROM (SELECT *, unnest(range(least(i1, i2)::BIGINT, greatest(i1, i2)::BIGINT)) AS r FROM best)
  UNION ALL SELECT t, klass, abs(j1 - a) + abs(i1 - i2) + CASE WHEN a < j2 THEN c - a ELSE a - 1 - c END, CASE WHEN a < j2 THEN 0 ELSE 6320 END + i2 * 79 + c, 100 + 10 * (i2 % 7)
    FROM (SELECT *, unnest(range(least(a, j2)::BIGINT, greatest(a, j2)::BIGINT)) AS c FROM best))"""


def g1_sql(span: int = 2) -> str:
    return f"WITH {paths_sql(span)} SELECT t, s::BIGINT AS s, count(*) AS n, max(length)::DOUBLE AS length FROM paths GROUP BY t, s"


#: Classes as row clusters, and as a column cluster the first class that uses a segment.
PLANTED_PARTS = f"g AS ({g1_sql()}), lab AS (SELECT t, klass FROM ({pairs_sql(2)})), r AS (SELECT t, klass::BIGINT AS ct FROM lab), c AS (SELECT s, min(ct) AS cs FROM g JOIN r USING (t) GROUP BY s)"
_BLOCK = "block AS (SELECT ct, cs, sum(n)::BIGINT AS m, count(*) AS edges FROM g JOIN r USING (t) JOIN c USING (s) GROUP BY 1, 2)"
_SHARES = "shares AS (SELECT ct, cs, m, m / sum(m) OVER () AS p, sum(m) OVER (PARTITION BY ct) / sum(m) OVER () AS pt, sum(m) OVER (PARTITION BY cs) / sum(m) OVER () AS ps FROM block), mi AS (SELECT *, pt * ps AS expected, p * ln(p / (pt * ps)) AS mi FROM shares)"


def planted_parts(spark: SparkSession, d: str, **options) -> tuple[BipartiteGraph, DataFrame, DataFrame]:
    graph, labels, _ = planted_graph(spark, d, **options)
    rows = labels.select(F.col("v").alias("t"), F.col("klass").cast("long").alias("ct"))
    columns = graph.traversal.join(rows, "t").groupBy("s").agg(F.min("ct").alias("cs"))
    return graph, rows, materialise(columns, "planted-columns")


def cost_sql(parts: str) -> str:
    """Every term of the code length, from ``g(t, s, n)``, ``r(t, ct)`` and ``c(s, cs)``."""
    return f"""WITH {parts}, {_BLOCK}, tv AS (SELECT t, sum(n) AS n FROM g GROUP BY 1), sv AS (SELECT s, sum(n) AS n FROM g GROUP BY 1),
tc AS (SELECT ct, count(*) AS size, sum(n) AS m, sum(lgamma(n + 1)) AS own FROM tv JOIN r USING (t) GROUP BY 1), sc AS (SELECT cs, count(*) AS size, sum(n) AS m, sum(lgamma(n + 1)) AS own FROM sv JOIN c USING (s) GROUP BY 1),
one AS (SELECT (SELECT sum(m) FROM block) AS m, (SELECT count(*) FROM tv) AS nt, (SELECT count(*) FROM sv) AS ns, (SELECT count(*) FROM tc) AS kt, (SELECT count(*) FROM sc) AS ks),
terms AS (SELECT ln(nt) + ln(ns) AS cluster_counts, {log_partitions_sql('(SELECT count(*) FROM tv)', '(SELECT count(*) FROM tc)')} + {log_partitions_sql('(SELECT count(*) FROM sv)', '(SELECT count(*) FROM sc)')} AS partitions,
  lgamma(m + kt * ks) - lgamma(kt * ks) - lgamma(m + 1) AS block_counts,
  (SELECT sum(lgamma(m + size) - lgamma(size) - lgamma(m + 1)) FROM tc) + (SELECT sum(lgamma(m + size) - lgamma(size) - lgamma(m + 1)) FROM sc) AS vertex_counts,
  lgamma(m + 1) - (SELECT sum(lgamma(m + 1)) FROM block) AS like_blocks, (SELECT sum(lgamma(m + 1) - own) FROM tc) + (SELECT sum(lgamma(m + 1) - own) FROM sc) AS like_margins FROM one)
SELECT {', '.join(f'round({x}, 3) + 0.0 AS {x}' for x in criterion.TERMS[:-1])}, round({' + '.join(criterion.TERMS[:-1])}, 3) AS total FROM terms"""


def _cost(cost: DataFrame) -> DataFrame:
    return cost.select(*[(F.round(x, 3) + F.lit(0.0)).alias(x) for x in criterion.TERMS])


def _one_block(graph: str) -> str:
    return f"g AS ({graph}), r AS (SELECT DISTINCT t, 0::BIGINT AS ct FROM g), c AS (SELECT DISTINCT s, 0::BIGINT AS cs FROM g)"


# routes and similarity


@add(f"WITH {paths_sql()} SELECT t, pos, s, klass FROM paths")
def planted_routes(spark, d):
    _, labels, paths = tables.planted(spark, d)
    return paths.join(labels.withColumnRenamed("v", "t"), "t")


@add(f"WITH {paths_sql(16)} SELECT t, pos, s, klass FROM paths")
def planted_routes_span16(spark, d):
    _, labels, paths = tables.planted(spark, d, span=16)
    return paths.join(labels.withColumnRenamed("v", "t"), "t")


@add(f"WITH {paths_sql()} SELECT count(DISTINCT s) AS visited, 14062 AS segments, round(count(DISTINCT s) / 14062, 6) AS share, count(DISTINCT t) AS trajectories, count(*) AS visits FROM paths")
def coverage_g1(spark, d):
    graph, _, _ = planted_graph(spark, d)
    return graph.coverage(network.segments(spark)).crossJoin(graph.stats().select("trajectories", "visits"))


@add(spatial_sql(g1_sql()))
def weight_spatial_g1(spark, d):
    return rounded(weights.spatial_tfidf(planted_graph(spark, d)[0]), "w")


@add(visit_sql(g1_sql()))
def weight_visit_g1(spark, d):
    return rounded(weights.visit_tfidf(planted_graph(spark, d)[0]), "w")


@add(cosine_sql(raw_weights(spatial_sql(g1_sql()))))
def cosine_t_g1(spark, d):
    return rounded(similarity.project(planted_graph(spark, d)[0], side="t").drop("common"), "omega", to=5)


@add(cosine_sql(raw_weights(visit_sql(g1_sql()))))
def cosine_s_g1(spark, d):
    return rounded(similarity.project(planted_graph(spark, d)[0], side="s").drop("common"), "omega", to=5)


@add(cosine_sql(raw_weights(spatial_sql(g1_sql(16)))))
def cosine_t_g1_span16(spark, d):
    return rounded(similarity.project(planted_graph(spark, d, span=16)[0], side="t").drop("common"), "omega", to=5)


def _edges_sql(span: int = 2) -> str:
    return cosine_sql(raw_weights(spatial_sql(g1_sql(span)))).replace("round(omega, 5) AS omega", "omega")


@add(f"WITH ends AS ({_edges_sql()}) SELECT v, count(*) AS degree, round(sum(omega), 4) AS strength FROM (SELECT a AS v, omega FROM ends UNION ALL SELECT b, omega FROM ends) GROUP BY v")
def symmetric_g1(spark, d):
    """Both directions of the projection: degree and strength of every trajectory."""
    both = similarity.symmetric(similarity.project(planted_graph(spark, d)[0], side="t"))
    return both.groupBy(F.col("a").alias("v")).agg(F.count(F.lit(1)).alias("degree"), F.round(F.sum("omega"), 4).alias("strength"))


def _modularity_sql(span: int) -> str:
    return f"""WITH w AS ({_edges_sql(span)}), lab AS (SELECT t AS v, klass AS c FROM ({pairs_sql(span)})), x AS (SELECT omega AS w, p.c AS ca, q.c AS cb FROM w JOIN lab p ON a = p.v JOIN lab q ON b = q.v),
k AS (SELECT c, sum(w) AS k FROM (SELECT ca AS c, w FROM x UNION ALL SELECT cb, w FROM x) GROUP BY c)
SELECT round((SELECT sum(CASE WHEN ca = cb THEN w ELSE 0 END) / sum(w) FROM x) - (SELECT sum(k * k) FROM k) / (4 * pow((SELECT sum(w) FROM x), 2)), 6) AS modularity"""


def _modularity(spark, d, span):
    graph, labels, _ = planted_graph(spark, d, span=span)
    return rounded(modularity.score(similarity.project(graph, side="t"), labels.select("v", F.col("klass").alias("c"))), "modularity")


@add(_modularity_sql(2))
def modularity_planted_g1(spark, d):
    """Modularity of the planted classes on the projection."""
    return _modularity(spark, d, 2)


@add(_modularity_sql(16))
def modularity_planted_span16(spark, d):
    return _modularity(spark, d, 16)


_PAIRS_G3 = cosine_sql(raw_weights(spatial_sql(G3))).replace("SELECT a, b, round(omega, 5) AS omega", "SELECT a, b, round(omega, 9) AS omega, common").replace("AS omega FROM w x", "AS omega, count(*) AS common FROM w x")


@add(
    f"""WITH pairs AS ({_PAIRS_G3}), ends AS (SELECT a, b, omega, common FROM pairs UNION ALL SELECT b, a, omega, common FROM pairs),
ranked AS (SELECT *, row_number() OVER (PARTITION BY a ORDER BY omega DESC, b) AS rank FROM ends) SELECT DISTINCT least(a, b) AS a, greatest(a, b) AS b, round(omega, 5) AS omega, common FROM ranked WHERE rank <= 3"""
)
def topk_similar_pairs(spark, d):
    """Flagship: the most similar customers of each by the parts they ordered."""
    best = similarity.strongest(similarity.project(tables.baskets(spark, d), side="t"), 3)
    # Nine places rank the pairs; the five shown are of those nine, as in the SQL.
    return rounded(rounded(best, "omega", to=9), "omega", to=5)


@add(
    f"""WITH e AS ({G4}), pairs AS (SELECT x.s AS a, y.s AS b FROM e x JOIN e y ON x.t = y.t AND x.s < y.s GROUP BY 1, 2), d AS (SELECT v, count(*) AS d FROM (SELECT a AS v FROM pairs UNION ALL SELECT b FROM pairs) GROUP BY v),
v AS (SELECT count(DISTINCT s) AS n FROM e) SELECT round(sum(d) / 2 / any_value(n * (n - 1) // 2), 6) AS density, quantile_cont(d, 0.5)::DOUBLE AS median_degree, max(d) AS max_degree FROM d, v"""
)
def projection_density_g4(spark, d):
    own = tables.shipments(spark, d)
    return rounded(similarity.density(similarity.project(own, side="s"), own.traversal.select("s").distinct().count()), "density")


@add(
    f"""WITH e AS ({G4}), r AS (SELECT t, string_agg(s || ':' || n, ',' ORDER BY s) AS k FROM e GROUP BY t), c AS (SELECT s, md5(string_agg(t || ':' || n, ',' ORDER BY t)) AS k FROM e GROUP BY s)
SELECT (SELECT count(*) FROM r) AS orders, (SELECT count(DISTINCT k) FROM r) AS row_clusters, (SELECT count(DISTINCT k) FROM c) AS column_clusters"""
)
def matched_start_g4(spark, d):
    """Vertices with equal neighbours begin in one cluster."""
    rows, columns = cocluster.matched_start(tables.shipments(spark, d))
    return rows.agg(F.count(F.lit(1)).alias("orders"), F.count_distinct("ct").alias("row_clusters")).crossJoin(columns.agg(F.count_distinct("cs").alias("column_clusters")))


_OWN = f"SELECT t, s, n FROM ({G8}) UNION ALL SELECT DISTINCT t, 1000 + t, 1 FROM ({G8})"


@add(
    f"""WITH e AS ({_OWN}), w AS (SELECT t AS v, s AS f, n * ln((SELECT count(DISTINCT t) FROM e)::DOUBLE / count(*) OVER (PARTITION BY s)) AS w FROM e), n AS (SELECT v, sqrt(sum(w * w)) AS norm FROM w GROUP BY v)
SELECT x.v AS a, y.v AS b, count(*) AS common, round(sum(x.w * y.w) / any_value(p.norm * q.norm), 5) + 0.0 AS omega FROM w x JOIN w y ON x.f = y.f AND x.v < y.v JOIN n p ON p.v = x.v JOIN n q ON q.v = y.v GROUP BY 1, 2"""
)
def keep_zero_edges_g8(spark, d):
    """Nations of customers by nations of suppliers, which nearly all share, and a segment of their own: edges that weigh nothing are kept."""
    own = tables.flows(spark, d).traversal.select("t", "s", "n")
    alone = own.select("t").distinct().select("t", (F.col("t") + 1000).alias("s"), F.lit(1).cast("long").alias("n"))
    graph = BipartiteGraph(own.unionByName(alone).withColumn("length", F.lit(1.0)))
    return rounded(similarity.project(graph, side="t", keep_zero=True).select("a", "b", "common", "omega"), "omega", to=5)


# code length


@add(cost_sql(PLANTED_PARTS))
def map_cost_planted_g1(spark, d):
    """Code length of the planted classes, with the first class that uses a segment as its cluster."""
    return _cost(criterion.cost(*planted_parts(spark, d)))


@add(cost_sql(_one_block(g1_sql())))
def map_cost_null_g1(spark, d):
    graph, _, _ = planted_graph(spark, d)
    return _cost(criterion.cost(graph, *criterion.null_model(graph)))


@add(cost_sql(_one_block(G8)))
def map_cost_null_g8(spark, d):
    graph = tables.flows(spark, d)
    return _cost(criterion.cost(graph, *criterion.null_model(graph)))


@add(cost_sql(_one_block(G3)))
def map_cost_null_g3(spark, d):
    graph = tables.baskets(spark, d)
    return _cost(criterion.cost(graph, *criterion.null_model(graph)))


def _fitted(model: cocluster.CoClustering) -> DataFrame:
    return model.block.crossJoin(model.cost().select(F.round("total", 3).alias("cost")))


def _one_block_fit(graph: str) -> str:
    return f"""WITH e AS ({graph}), cost AS ({cost_sql(_one_block(graph))})
SELECT min(t) AS ct, min(s) AS cs, sum(n)::BIGINT AS m, count(*) AS edges, any_value(total) AS cost FROM e, cost"""


@add(_one_block_fit(G8))
def cocluster_g8(spark, d):
    """Flows without structure: the search ends at one block, at the cost of one block."""
    return _fitted(cocluster.fit(tables.flows(spark, d)))


@add(_one_block_fit(G3))
def null_control_g3(spark, d):
    """Baskets without structure: one block too."""
    return _fitted(cocluster.fit(tables.baskets(spark, d), restarts=1))


# blocks of the planted classes


@add(f"WITH {PLANTED_PARTS}, {_BLOCK}, {_SHARES} SELECT ct, cs, m, round(p, 6) AS p, round(expected, 6) AS expected, round(mi, 6) AS mi FROM mi")
def mi_planted_g1(spark, d):
    return rounded(mutual.contributions(mutual.crossed(*planted_parts(spark, d))).select("ct", "cs", "m", "p", "expected", "mi"), "p", "expected", "mi")


@add(f"WITH {PLANTED_PARTS}, {_BLOCK}, {_SHARES} SELECT round(sum(mi), 6) AS mutual_information FROM mi")
def mi_total_planted_g1(spark, d):
    return rounded(mutual.total(mutual.contributions(mutual.crossed(*planted_parts(spark, d)))), "mutual_information")


@add(
    f"""WITH {PLANTED_PARTS}, {_BLOCK}, sizes AS (SELECT ct, count(*) AS rows FROM r GROUP BY ct), wide AS (SELECT cs, count(*) AS columns FROM c GROUP BY cs),
used AS (SELECT ct, cs, s, count(*) AS edges, count(*)::DOUBLE / any_value(rows) AS fill FROM g JOIN r USING (t) JOIN c USING (s) JOIN sizes USING (ct) GROUP BY ct, cs, s)
SELECT ct, cs, sum(edges)::BIGINT AS edges, round(sum(edges) / any_value(rows * columns), 6) AS density, round(sqrt(greatest(sum(fill * fill) / any_value(columns) - pow(sum(fill) / any_value(columns), 2), 0)), 6) AS dispersion
FROM used JOIN sizes USING (ct) JOIN wide USING (cs) GROUP BY ct, cs"""
)
def homogeneity_planted_g1(spark, d):
    """Density of the planted blocks, and how unevenly their segments are used."""
    return rounded(mutual.profile(*planted_parts(spark, d)), "density", "dispersion")


@add(
    f"""WITH {PLANTED_PARTS}, rows AS (SELECT t, ct, row_number() OVER (ORDER BY ct, count(*) DESC, t) AS row_rank FROM g JOIN r USING (t) GROUP BY t, ct), columns AS (SELECT s, cs, row_number() OVER (ORDER BY cs, count(*) DESC, s) AS col_rank FROM g JOIN c USING (s) GROUP BY s, cs)
SELECT row_rank, col_rank, n, ct, cs FROM g JOIN rows USING (t) JOIN columns USING (s)"""
)
def reordered_planted_g1(spark, d):
    return mutual.reordered(*planted_parts(spark, d))


def roles_sql(parts: str) -> str:
    return f"""WITH {parts}, {_BLOCK}, {_SHARES}, of AS (SELECT cs, sum(m)::BIGINT AS visits, -sum(share * ln(share)) AS entropy, max(mi) - min(mi) AS contrast, stddev_pop(mi) AS spread FROM (SELECT *, m / sum(m) OVER (PARTITION BY cs) AS share FROM mi) GROUP BY cs),
even AS (SELECT *, entropy / ln(greatest((SELECT count(DISTINCT ct) FROM block), 2)) AS evenness, percent_rank() OVER (ORDER BY visits) AS rank FROM of)
SELECT cs, visits, round(entropy, 6) + 0.0 AS entropy, round(contrast, 6) AS contrast, round(spread, 6) AS spread, round(evenness, 6) + 0.0 AS evenness, CASE WHEN evenness >= 0.7 THEN 'hub' WHEN rank <= 0.25 THEN 'rare' ELSE 'secondary' END AS role FROM even"""


def _roles(block: DataFrame) -> DataFrame:
    found = rounded(mutual.roles(block), "entropy", "contrast", "spread", "evenness")
    return found.withColumns({c: F.col(c) + F.lit(0.0) for c in ("entropy", "evenness")}).select("cs", "visits", "entropy", "contrast", "spread", "evenness", "role")


@add(roles_sql(PLANTED_PARTS))
def roles_planted_g1(spark, d):
    """Roles of the segments by the first class that uses them."""
    return _roles(mutual.crossed(*planted_parts(spark, d)))


@add(roles_sql(f"g AS ({G4}), r AS (SELECT o_orderkey AS t, n_regionkey::BIGINT AS ct FROM orders JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey), c AS (SELECT DISTINCT s, s AS cs FROM g)"))
def roles_g4(spark, d):
    """Suppliers by the regions whose orders they serve: a supplier is a segment cluster of its own."""
    graph = tables.shipments(spark, d)
    people = table(spark, d, "customer").join(table(spark, d, "nation"), F.col("c_nationkey") == F.col("n_nationkey")).select("c_custkey", F.col("n_regionkey").cast("long").alias("ct"))
    rows = table(spark, d, "orders").join(people, F.col("o_custkey") == F.col("c_custkey")).select(F.col("o_orderkey").cast("long").alias("t"), "ct")
    return _roles(mutual.crossed(graph, rows, graph.traversal.select("s").distinct().withColumn("cs", F.col("s"))))


_WORDS = r"SELECT doc_id, word, count(*) AS n FROM (SELECT doc_id, unnest(regexp_extract_all(lower(text), '[\p{L}]+')) AS word FROM documents) GROUP BY 1, 2"
_SPOKEN = f"g AS (SELECT doc_id AS t, word AS s, n FROM ({_WORDS})), r AS (SELECT doc_id AS t, lang AS ct FROM documents), c AS (SELECT s, count(DISTINCT ct) AS cs FROM g JOIN r USING (t) GROUP BY s)"


def _spoken(spark, d) -> tuple[BipartiteGraph, DataFrame, DataFrame]:
    """Documents by language, and words by the number of languages that have them."""
    words = tables.word_rows(spark, d).select(F.col("doc_id").alias("t"), F.col("word").alias("s"), "n")
    graph = BipartiteGraph(materialise(words, "words"))
    rows = table(spark, d, "documents").select(F.col("doc_id").alias("t"), F.col("lang").alias("ct"))
    return graph, rows, graph.traversal.join(rows, "t").groupBy("s").agg(F.count_distinct("ct").alias("cs"))


@add(f"WITH {_SPOKEN}, {_BLOCK}, {_SHARES} SELECT ct, cs, m, round(p, 6) AS p, round(expected, 6) AS expected, round(mi, 6) AS mi FROM mi")
def mi_lang_g2(spark, d):
    """Mutual information of languages and of how many of them share a word."""
    return rounded(mutual.contributions(mutual.crossed(*_spoken(spark, d))).select("ct", "cs", "m", "p", "expected", "mi"), "p", "expected", "mi")


@add(roles_sql(_SPOKEN))
def roles_g2(spark, d):
    """Words that all languages have are the hubs."""
    return _roles(mutual.crossed(*_spoken(spark, d)))


# optima of small graphs, against every partition there is

_EVERY = """every AS (SELECT row_number() OVER () AS id, [0, b, c, d, e] AS label FROM (SELECT unnest(range(2)) AS b), (SELECT unnest(range(3)) AS c), (SELECT unnest(range(4)) AS d), (SELECT unnest(range(5)) AS e)
  WHERE c <= b + 1 AND d <= greatest(b, c) + 1 AND e <= greatest(b, c, d) + 1)"""


def _best_communities(edges: str) -> str:
    """Of the 52 partitions of five vertices the one of most modularity, from ``edges`` of (a, b, w)."""
    return f"""WITH g AS ({edges}), ids AS (SELECT v, row_number() OVER (ORDER BY v) AS i FROM (SELECT a AS v FROM g UNION SELECT b FROM g)), {_EVERY},
lab AS (SELECT id, v, label[i::INT] AS c FROM every, ids), x AS (SELECT p.id, w, p.c AS ca, q.c AS cb FROM g JOIN lab p ON a = p.v JOIN lab q ON b = q.v AND q.id = p.id),
k AS (SELECT id, sum(k * k) AS k FROM (SELECT id, c, sum(w) AS k FROM (SELECT id, ca AS c, w FROM x UNION ALL SELECT id, cb, w FROM x) GROUP BY id, c) GROUP BY id),
q AS (SELECT id, sum(CASE WHEN ca = cb THEN w ELSE 0 END) / sum(w) - any_value(k) / (4 * pow(sum(w), 2)) AS q FROM x JOIN k USING (id) GROUP BY id), best AS (SELECT id, q FROM q ORDER BY round(q, 9) DESC, id LIMIT 1)
SELECT v, min(v) OVER (PARTITION BY c) AS c, round(q, 6) AS modularity FROM lab JOIN best USING (id)"""


def _found_communities(edges: DataFrame) -> DataFrame:
    own = materialise(edges, "small-edges")
    part = materialise(modularity.communities(own), "small-part")
    return part.crossJoin(rounded(modularity.score(own, part), "modularity"))


_CLASS_EDGES = f"SELECT least(p.c, q.c) AS a, greatest(p.c, q.c) AS b, sum(omega) AS w FROM ({_edges_sql(16)}) w JOIN (SELECT t AS v, klass::BIGINT AS c FROM ({pairs_sql(16)})) p ON a = p.v JOIN (SELECT t AS v, klass::BIGINT AS c FROM ({pairs_sql(16)})) q ON b = q.v WHERE p.c <> q.c GROUP BY 1, 2"


@add(_best_communities(_CLASS_EDGES))
def communities_of_classes(spark, d):
    """Classes as vertices, with the similarity between their trajectories: the best of all partitions is found."""
    graph, labels, _ = planted_graph(spark, d, span=16)
    klass = labels.select("v", F.col("klass").cast("long").alias("c"))
    between = modularity.contract(similarity.project(graph, side="t"), klass).where("a <> b")
    return _found_communities(between)


@add(_best_communities(f"WITH f AS ({G8}), reg AS (SELECT n_nationkey::BIGINT AS n, n_regionkey::BIGINT AS r FROM nation) SELECT least(p.r, q.r) AS a, greatest(p.r, q.r) AS b, sum(f.n)::DOUBLE AS w FROM f JOIN reg p ON f.t = p.n JOIN reg q ON f.s = q.n WHERE p.r <> q.r GROUP BY 1, 2"))
def communities_of_regions(spark, d):
    """Regions with the order lines between them."""
    region = table(spark, d, "nation").select(F.col("n_nationkey").cast("long").alias("v"), F.col("n_regionkey").cast("long").alias("c"))
    flows = tables.flows(spark, d).traversal.select(F.col("t").alias("a"), F.col("s").alias("b"), F.col("n").cast("double").alias("omega"))
    return _found_communities(modularity.contract(flows, region).where("a <> b"))


def _best_blocks(cells: str) -> str:
    """Of all pairs of partitions of five rows and five columns the one of least code length, from ``cells`` of (t, s, n)."""

    def side(v: str, x: str) -> str:
        return f"""{x}i AS (SELECT {v} AS v, sum(n) AS n, row_number() OVER (ORDER BY {v}) AS i FROM g GROUP BY {v}), {x} AS (SELECT id, v, n, label[i::INT] AS c FROM every, {x}i),
{x}k AS (SELECT id, count(*) AS k, sum(lgamma(m + size) - lgamma(size) - own) AS cost FROM (SELECT id, c, count(*) AS size, sum(n) AS m, sum(lgamma(n + 1)) AS own FROM {x} GROUP BY id, c) GROUP BY id)"""

    ways = "ln([1, 16, 41, 51, 52][{}.k::INT])"
    return f"""WITH g AS ({cells}), {_EVERY}, {side('t', 'r')}, {side('s', 'k')},
blocks AS (SELECT p, q, sum(lgamma(m + 1)) AS f FROM (SELECT r.id AS p, k.id AS q, r.c AS a, k.c AS b, sum(g.n) AS m FROM g JOIN r ON g.t = r.v JOIN k ON g.s = k.v GROUP BY ALL) GROUP BY p, q),
costs AS (SELECT p, q, 2 * ln(5) + {ways.format('rk')} + {ways.format('kk')} + lgamma(m + rk.k * kk.k) - lgamma(rk.k * kk.k) - lgamma(m + 1) + rk.cost + kk.cost + lgamma(m + 1) - f AS cost
  FROM blocks JOIN rk ON p = rk.id JOIN kk ON q = kk.id, (SELECT sum(n) AS m FROM g)), best AS (SELECT * FROM costs ORDER BY round(cost, 6), p, q LIMIT 1)
SELECT 't' AS side, v, min(v) OVER (PARTITION BY c) AS c, round(cost, 3) AS cost FROM r JOIN best ON id = p UNION ALL SELECT 's', v, min(v) OVER (PARTITION BY c), round(cost, 3) FROM k JOIN best ON id = q"""


def _found_blocks(block: DataFrame) -> DataFrame:
    model = cocluster.fit(BipartiteGraph.of(block.select(F.col("ct").alias("t"), F.col("cs").alias("s"), F.col("m").alias("n")), length=None))
    sides = [p.select(F.lit(v).alias("side"), F.col(v).alias("v"), F.col(c).alias("c")) for p, v, c in ((model.row_part, "t", "ct"), (model.col_part, "s", "cs"))]
    return sides[0].unionByName(sides[1]).crossJoin(model.cost().select(F.round("total", 3).alias("cost")))


@add(_best_blocks(f"WITH {PLANTED_PARTS}, {_BLOCK} SELECT ct AS t, cs AS s, m AS n FROM block"))
def cocluster_of_classes(spark, d):
    """Classes by the first class of their segments: the co-clustering found is the best of all 2,704."""
    return _found_blocks(mutual.crossed(*planted_parts(spark, d)))


@add(_best_blocks(f"WITH f AS ({G8}), reg AS (SELECT n_nationkey::BIGINT AS n, n_regionkey::BIGINT AS r FROM nation) SELECT p.r AS t, q.r AS s, sum(f.n) AS n FROM f JOIN reg p ON f.t = p.n JOIN reg q ON f.s = q.n GROUP BY 1, 2"))
def cocluster_of_regions(spark, d):
    """Regions of customers by regions of suppliers."""
    region = table(spark, d, "nation").select(F.col("n_nationkey").cast("long").alias("t"), F.col("n_regionkey").cast("long").alias("ct"))
    return _found_blocks(mutual.crossed(tables.flows(spark, d), region, region.select(F.col("t").alias("s"), F.col("ct").alias("cs"))))


@add(_best_blocks("SELECT customer_segment AS t, kind AS s, count(*) AS n FROM (SELECT list_position(['AUTOMOBILE', 'BUILDING', 'FURNITURE', 'HOUSEHOLD', 'MACHINERY'], c_mktsegment) AS customer_segment, CASE WHEN list_position(['AUTOMOBILE', 'BUILDING', 'FURNITURE', 'HOUSEHOLD', 'MACHINERY'], c_mktsegment) <= 2 AND o_orderkey % 3 > 0 THEN o_orderkey % 2 ELSE 2 + o_orderkey % 3 END AS kind FROM orders JOIN customer ON o_custkey = c_custkey) GROUP BY 1, 2"))
def cocluster_of_market_segments(spark, d):
    """Market segments by a kind of order that two of them prefer: structure in five rows and columns."""
    names = F.array(*[F.lit(x) for x in ("AUTOMOBILE", "BUILDING", "FURNITURE", "HOUSEHOLD", "MACHINERY")])
    own = table(spark, d, "orders").join(table(spark, d, "customer"), F.col("o_custkey") == F.col("c_custkey")).withColumn("ct", F.array_position(names, F.col("c_mktsegment")))
    own = own.withColumn("cs", F.when((F.col("ct") <= 2) & (F.col("o_orderkey") % 3 > 0), F.col("o_orderkey") % 2).otherwise(2 + F.col("o_orderkey") % 3))
    return _found_blocks(own.groupBy("ct", "cs").agg(F.count(F.lit(1)).alias("m")))
