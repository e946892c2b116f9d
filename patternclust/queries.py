"""Registered queries on the graph corpora, with the SQL that must give the same rows."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from . import corpora
from .functions.binomial import decision_column
from .functions.fingerprint import fingerprint, may_contain, with_fingerprint
from .functions.patterns import has_edge, triple_keys
from .model import Graph
from .operators import graph_stats as gs
from .operators import measures, probe, scan, vectors
from .planted import planted_truth
from .plans.state import commit
from .sources.tables import table

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
ORACLES: dict[str, str] = {}


def query(sql: str | None = None, name: str | None = None):
    def add(f: Query) -> Query:
        key = name or f.__name__
        QUERIES[key] = f
        if sql:
            ORACLES[key] = sql
        return f

    return add


# SQL views of the corpora
ORDER = """
li AS (SELECT l_orderkey AS g, 'p' || l_partkey AS p, l_partkey, 's' || l_suppkey AS s, l_suppkey, l_returnflag AS rf, l_linestatus AS ls FROM lineitem),
ov AS (
  SELECT o_orderkey AS g, 'o' AS v, o_orderpriority AS l FROM orders WHERE o_orderkey IN (SELECT g FROM li)
  UNION SELECT g, p, p_type FROM li JOIN part ON l_partkey = p_partkey
  UNION SELECT g, s, r_name FROM li JOIN supplier ON l_suppkey = s_suppkey JOIN nation ON s_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey
),
oe AS (
  SELECT g, 'o' AS a, p AS b, min(rf) AS l FROM li GROUP BY g, p
  UNION ALL SELECT g, p AS a, s AS b, min(ls) AS l FROM li GROUP BY g, p, s
),
og AS (SELECT v.g, v.n_v, coalesce(e.n_e, 0) AS n_e, v.n_v + coalesce(e.n_e, 0) AS gsize
       FROM (SELECT g, count(*) AS n_v FROM ov GROUP BY g) v LEFT JOIN (SELECT g, count(*) AS n_e FROM oe GROUP BY g) e ON v.g = e.g),
ot AS (SELECT e.g, e.a, x.l AS la, e.l AS le, e.b, y.l AS lb FROM oe e JOIN ov x ON x.g = e.g AND x.v = e.a JOIN ov y ON y.g = e.g AND y.v = e.b)
"""
PROBE = ORDER + """,
reg AS (SELECT unnest([1, 2, 3, 4, 5]) AS c, unnest(['AFRICA', 'AMERICA', 'ASIA', 'EUROPE', 'MIDDLE EAST']) AS r),
hits AS (
  SELECT DISTINCT g, c, 1 AS rep, 3 AS rsize FROM ot JOIN reg ON la = 'STANDARD' AND le = 'O' AND lb = r
  UNION ALL SELECT DISTINCT g, c, 2, 3 FROM ot JOIN reg ON la = 'PROMO' AND le = 'F' AND lb = r
  UNION ALL SELECT DISTINCT x.g, c, 3, 5 FROM ot x JOIN ot y ON x.g = y.g AND x.b = y.a JOIN reg ON y.lb = r
    WHERE x.la = '5-LOW' AND x.le = 'R' AND x.lb = 'MEDIUM' AND y.le = 'O'
),
reps AS (SELECT c, rep, rsize FROM reg, (SELECT unnest([1, 2, 3]) AS rep, unnest([3, 3, 5]) AS rsize)),
sim AS (SELECT g, c, sum(rsize * rsize) AS similarity, sum(rsize) AS linear FROM hits GROUP BY g, c),
asg AS (SELECT og.g, og.gsize, coalesce(b.c, -1) AS c, coalesce(b.similarity, 0) AS similarity FROM og
        LEFT JOIN (SELECT * FROM (SELECT *, row_number() OVER (PARTITION BY g ORDER BY similarity DESC, c) AS k FROM sim) WHERE k = 1) b ON og.g = b.g),
hc AS (SELECT a.c, count(*) AS n, 11.0 / 3 / avg(gsize) AS hcov FROM asg a WHERE c > 0 GROUP BY a.c),
rk AS (
  SELECT h.c, h.rep, h.rsize, count(*) FILTER (WHERE a.c = h.c) AS n_sup_c, count(*) FILTER (WHERE a.c = h.c) / any_value(s.n)::DOUBLE AS supp_c,
         count(*) / (SELECT count(*) FROM og)::DOUBLE AS supp_d,
         h.rsize / avg(a.gsize) FILTER (WHERE a.c = h.c) * (count(*) FILTER (WHERE a.c = h.c) / any_value(s.n)::DOUBLE - count(*) / (SELECT count(*) FROM og)::DOUBLE) AS rank
  FROM hits h JOIN asg a ON h.g = a.g JOIN (SELECT c, count(*) AS n FROM asg GROUP BY c) s ON s.c = h.c GROUP BY h.c, h.rep, h.rsize
)
"""
SESSION = """
sx AS (SELECT user_id * 100 + week(ts) AS g, event_id, event_type, ts FROM events),
sl AS (SELECT *, lag(event_id) OVER (PARTITION BY g ORDER BY ts, event_id) AS p, lag(event_id) OVER (PARTITION BY g, event_type ORDER BY ts, event_id) AS q FROM sx),
sv AS (SELECT g, event_id::VARCHAR AS v, event_type AS l FROM sx),
se AS (SELECT g, p::VARCHAR AS a, event_id::VARCHAR AS b, 'next' AS l FROM sl WHERE p IS NOT NULL
       UNION ALL SELECT g, q::VARCHAR, event_id::VARCHAR, 'same' FROM sl WHERE q IS NOT NULL AND q <> p)
"""
_listed = ", ".join(f"'{w}'" for own in corpora.LISTED_WORDS.values() for w in own)
DOCS = rf"""
dw AS (SELECT doc_id AS g, list_transform(regexp_extract_all(lower(text), '(\p{{L}}+)', 1), lambda w: CASE WHEN w IN ({_listed}) THEN w ELSE '*' || least(6, (length(w) + 1) // 2) END) AS t FROM documents),
dt AS (SELECT g, t FROM dw WHERE len(t) > 0),
dv AS (SELECT g, unnest(list_distinct(t)) AS l FROM dt),
dp AS (SELECT g, t, unnest(range(1, len(t) + 1)) AS i FROM dt),
dn AS (SELECT g, x, y, s, count(*) AS n FROM (SELECT g, t[i] AS x, t[i + 1] AS y, 'a' AS s FROM dp WHERE i + 1 <= len(t) UNION ALL SELECT g, t[i], t[i + 2], 's' FROM dp WHERE i + 2 <= len(t)) WHERE x <> y GROUP BY g, x, y, s),
df AS (SELECT g, x, y, s FROM (SELECT *, row_number() OVER (PARTITION BY g, x, s ORDER BY n DESC, y) AS k FROM dn) WHERE k = 1),
de AS (SELECT g, least(x, y) AS a, greatest(x, y) AS b, min(s) AS l FROM df GROUP BY g, least(x, y), greatest(x, y))
"""
CONV = """
cx AS (SELECT DISTINCT conv_id, turn, role FROM conversations),
cl AS (SELECT *, lag(turn, 1) OVER w AS p1, lag(turn, 2) OVER w AS p2, lag(role, 2) OVER w AS r2 FROM cx WINDOW w AS (PARTITION BY conv_id ORDER BY turn)),
cv AS (SELECT conv_id AS g, turn::VARCHAR AS v, role AS l FROM cx),
ce AS (SELECT conv_id AS g, p1::VARCHAR AS a, turn::VARCHAR AS b, 'next' AS l FROM cl WHERE p1 IS NOT NULL
       UNION ALL SELECT conv_id, p2::VARCHAR, turn::VARCHAR, 'same' FROM cl WHERE p2 IS NOT NULL AND r2 = role)
"""


def _stats_sql(views: str, v: str, e: str) -> str:
    return f"""WITH {views}, sizes AS (
  SELECT x.g, x.n_v, coalesce(y.n_e, 0) AS n_e FROM (SELECT g, count(*) AS n_v FROM {v} GROUP BY g) x LEFT JOIN (SELECT g, count(*) AS n_e FROM {e} GROUP BY g) y ON x.g = y.g)
SELECT count(*) AS n_graphs, min(n_v) AS v_min, max(n_v) AS v_max, round(avg(n_v), 6) AS v_avg, min(n_e) AS e_min, max(n_e) AS e_max, round(avg(n_e), 6) AS e_avg,
       (SELECT count(DISTINCT l) FROM {v}) AS n_vlabels, (SELECT count(DISTINCT l) FROM {e}) AS n_elabels FROM sizes"""


def _graphs(spark, sf, name="order"):
    return corpora.graphs(spark, sf, name)


for _name, _views, _v, _e in (("order", ORDER, "ov", "oe"), ("session", SESSION, "sv", "se"), ("doc", DOCS, "dv", "de"), ("conv", CONV, "cv", "ce")):
    query(_stats_sql(_views, _v, _e), f"{_name}_graph_stats")(lambda spark, sf, _name=_name: gs.describe(_graphs(spark, sf, _name)))


@query()
def dom_graph_stats(spark, sf):
    return gs.describe(_graphs(spark, sf, "dom"))


@query(f"WITH {ORDER} SELECT g, n_v, n_e, gsize FROM og")
def order_graph_sizes(spark, sf):
    return gs.sizes(_graphs(spark, sf))


@query(f"WITH {ORDER} SELECT l, count(DISTINCT g) AS n_support, round(count(DISTINCT g) / (SELECT count(*) FROM og)::DOUBLE, 6) AS supp FROM ov GROUP BY l HAVING count(DISTINCT g) / (SELECT count(*) FROM og)::DOUBLE >= 0.4")
def order_frequent_vertices(spark, sf):
    return gs.frequent_vertices(_graphs(spark, sf), 0.4)


FREQUENT_PATHS = """fp AS (SELECT least(la, lb) AS la, le, greatest(la, lb) AS lb, count(DISTINCT g) AS n_support, count(DISTINCT g) / (SELECT count(*) FROM og)::DOUBLE AS supp
  FROM ot GROUP BY least(la, lb), le, greatest(la, lb) HAVING count(DISTINCT g) / (SELECT count(*) FROM og)::DOUBLE >= 0.045)"""


@query(f"WITH {ORDER}, {FREQUENT_PATHS} SELECT la, le, lb, n_support, round(supp, 6) AS supp FROM fp")
def order_frequent_paths(spark, sf):
    return gs.frequent_paths(_graphs(spark, sf), 0.045)


def _reps(spark):
    return spark.createDataFrame([(p.cluster_id, p.rep_id, p.size) for p in probe.region_probes()], "cluster_id int, rep_id int, rsize int")


def _hits(spark, sf):
    return probe.hit_rows(_graphs(spark, sf), probe.region_probes())


def _assigned(spark, sf):
    return probe.assign(_graphs(spark, sf), probe.region_probes())


@query(f"""WITH {PROBE} SELECT reps.c AS cluster_id, reps.rep AS rep_id, reps.rsize, count(h.g) AS n_support, round(count(h.g) / (SELECT count(*) FROM og)::DOUBLE, 6) AS supp
FROM reps LEFT JOIN hits h ON h.c = reps.c AND h.rep = reps.rep GROUP BY reps.c, reps.rep, reps.rsize""")
def order_pattern_support(spark, sf):
    g = _graphs(spark, sf)
    n = g.agg(F.count(F.lit(1)).alias("n"))
    counted = _hits(spark, sf).groupBy("cluster_id", "rep_id").agg(F.count(F.lit(1)).alias("s"))
    s = F.coalesce("s", F.lit(0)).cast("bigint")
    return _reps(spark).join(counted, ["cluster_id", "rep_id"], "left").crossJoin(F.broadcast(n)).select("cluster_id", "rep_id", "rsize", s.alias("n_support"), F.round(s / F.col("n"), 6).alias("supp"))


@query(f"""WITH {PROBE}, n AS (SELECT count(*)::DOUBLE AS n FROM og), s AS (
  SELECT c, (SELECT count(DISTINCT g) FROM ot WHERE la = '5-LOW' AND le = 'R' AND lb = 'MEDIUM') AS s1,
         (SELECT count(DISTINCT g) FROM ot WHERE la = 'MEDIUM' AND le = 'O' AND lb = r) AS s2, (SELECT count(*) FROM hits WHERE hits.c = reg.c AND rep = 3) AS s3 FROM reg)
SELECT c AS cluster_id, round(s1 / n, 6) AS s_sub1, round(s2 / n, 6) AS s_sub2, round(s3 / n, 6) AS s_full, s3 <= s1 AND s3 <= s2 AS holds FROM s, n""")
def order_monotonicity(spark, sf):
    flags = F.array(*[F.struct(F.lit(p.cluster_id).alias("c"), has_edge(*p.edges[0]).alias("a"), has_edge(*p.edges[1]).alias("b"), p.hit.alias("f")) for p in probe.region_probes() if p.rep_id == 3])
    share = lambda c: F.avg(F.col(f"x.{c}").cast("int"))
    per = _graphs(spark, sf).select(F.explode(flags).alias("x")).groupBy(F.col("x.c").alias("cluster_id")).agg(share("a").alias("a"), share("b").alias("b"), share("f").alias("f"))
    return per.select("cluster_id", F.round("a", 6).alias("s_sub1"), F.round("b", 6).alias("s_sub2"), F.round("f", 6).alias("s_full"), ((F.col("f") <= F.col("a")) & (F.col("f") <= F.col("b"))).alias("holds"))


@query(f"""WITH {PROBE} SELECT c AS cluster_id, rep AS rep_id, round(min(rsize / gsize::DOUBLE), 6) AS cov_min, round(avg(rsize / gsize::DOUBLE), 6) AS cov_avg, round(max(rsize / gsize::DOUBLE), 6) AS cov_max
FROM hits JOIN og ON hits.g = og.g GROUP BY c, rep""")
def order_coverage(spark, sf):
    c = F.col("rsize") / F.col("gsize")
    return _hits(spark, sf).groupBy("cluster_id", "rep_id").agg(F.round(F.min(c), 6).alias("cov_min"), F.round(F.avg(c), 6).alias("cov_avg"), F.round(F.max(c), 6).alias("cov_max"))


@query(f"WITH {PROBE} SELECT g, c AS cluster_id, similarity::BIGINT AS similarity FROM sim")
def order_similarity(spark, sf):
    each = probe.similarities(_graphs(spark, sf), probe.region_probes()).select("graph_id", F.explode("scored").alias("x"))
    return each.select(F.col("graph_id").alias("g"), (-F.col("x.minus")).alias("cluster_id"), F.col("x.similarity").alias("similarity"))


@query(f"WITH {PROBE} SELECT g, c AS cluster_id, similarity::BIGINT AS similarity FROM asg")
def order_assign(spark, sf):
    return _assigned(spark, sf).select(F.col("graph_id").alias("g"), "cluster_id", "similarity")


@query(f"""WITH {PROBE} SELECT og.g, coalesce(b.c, -1) AS cluster_id, coalesce(b.linear, 0)::BIGINT AS similarity FROM og
LEFT JOIN (SELECT * FROM (SELECT *, row_number() OVER (PARTITION BY g ORDER BY linear DESC, c) AS k FROM sim) WHERE k = 1) b ON og.g = b.g""")
def order_assign_linear(spark, sf):
    return probe.assign(_graphs(spark, sf), probe.region_probes(), power=1).select(F.col("graph_id").alias("g"), "cluster_id", "similarity")


@query(f"WITH {PROBE} SELECT count(*) FILTER (WHERE c = -1) AS n_noise, round(count(*) FILTER (WHERE c = -1) / count(*)::DOUBLE, 6) AS share FROM asg")
def order_noise(spark, sf):
    noise = F.count(F.when(F.col("cluster_id") == -1, 1))
    return _assigned(spark, sf).agg(noise.alias("n_noise"), F.round(noise / F.count(F.lit(1)), 6).alias("share"))


@query(f"WITH {PROBE} SELECT c AS cluster_id, count(*) AS n, sum(gsize)::BIGINT AS sum_gsize FROM asg GROUP BY c")
def order_cluster_stats(spark, sf):
    return probe.cluster_stats(_assigned(spark, sf))


@query(f"WITH {PROBE} SELECT c AS cluster_id, rep AS rep_id, n_sup_c, round(supp_c, 6) AS supp_c, round(supp_d, 6) AS supp_d, round(rank, 6) AS rank FROM rk")
def order_rank(spark, sf):
    return _ranked(spark, sf).select("cluster_id", "rep_id", "n_sup_c", F.round("supp_c", 6).alias("supp_c"), F.round("supp_d", 6).alias("supp_d"), F.round("rank", 6).alias("rank"))


def _both(spark, sf):
    """Assignment and hits from one corpus, written once."""
    g = commit(_graphs(spark, sf), "orders")
    return probe.assign(g, probe.region_probes()), probe.hit_rows(g, probe.region_probes())


def _ranked(spark, sf):
    return probe.ranks(*_both(spark, sf))


TOP2 = "top2 AS (SELECT c, rep, k FROM (SELECT *, row_number() OVER (PARTITION BY c ORDER BY round(rank, 9) DESC NULLS LAST, rsize DESC, rep) AS k FROM rk) WHERE k <= 2)"


@query(f"WITH {PROBE}, {TOP2} SELECT c AS cluster_id, rep AS rep_id, k::INTEGER AS rk FROM top2")
def order_top_reps(spark, sf):
    return probe.top_representatives(_ranked(spark, sf), 2).select("cluster_id", "rep_id", "rk")


@query(f"WITH {PROBE} SELECT c AS cluster_id, round(hcov, 6) AS hcov FROM hc")
def order_hcov(spark, sf):
    return probe.hcov(_assigned(spark, sf), _reps(spark)).select("cluster_id", F.round("hcov", 6).alias("hcov"))


RELCOV = "rc AS (SELECT c, n, hcov, hcov / (SELECT avg(hcov) FROM hc) AS relcov FROM hc)"


@query(f"""WITH {PROBE}, {RELCOV} SELECT c AS cluster_id, round(relcov, 6) AS relcov,
 round(CASE WHEN relcov < 0 THEN 0.4 WHEN relcov > 0.9 THEN 0.99 ELSE 0.4 + relcov * (0.59 / 0.9) END, 6) AS minsup,
 round(CASE WHEN relcov < 0 THEN 0.4 WHEN relcov > 1.05 THEN 0.99 ELSE 0.4 + relcov * (0.59 / 1.05) END, 6) AS minsup_wide FROM rc""")
def order_relcov_minsup(spark, sf):
    r = probe.relcov(probe.hcov(_assigned(spark, sf), _reps(spark)))
    return r.select("cluster_id", F.round("relcov", 6).alias("relcov"), F.round(probe.minsup_of(F.col("relcov")), 6).alias("minsup"), F.round(probe.minsup_of(F.col("relcov"), hr=1.05), 6).alias("minsup_wide"))


@query(f"WITH {PROBE}, {RELCOV} SELECT c AS cluster_id, round(relcov, 6) AS relcov FROM rc WHERE relcov <= 0.98")
def order_split_candidates(spark, sf):
    r = probe.relcov(probe.hcov(_assigned(spark, sf), _reps(spark)))
    return r.where("relcov <= 0.98").select("cluster_id", F.round("relcov", 6).alias("relcov"))


@query(f"""WITH {PROBE}, {TOP2}, m AS (SELECT a.c, a.g, count(t.rep) AS k FROM asg a LEFT JOIN hits h ON h.g = a.g AND h.c = a.c LEFT JOIN top2 t ON t.c = a.c AND t.rep = h.rep WHERE a.c > 0 GROUP BY a.c, a.g)
SELECT c AS cluster_id, count(*) FILTER (WHERE k = 0) AS n_unsupported, round(count(*) FILTER (WHERE k = 0) / count(*)::DOUBLE, 6) AS share FROM m GROUP BY c""")
def order_unsupported(spark, sf):
    assigned, hits = _both(spark, sf)
    best = probe.top_representatives(probe.ranks(assigned, hits), 2).select("cluster_id", "rep_id")
    kept = hits.join(best, ["cluster_id", "rep_id"]).select("graph_id", "cluster_id").distinct().withColumn("kept", F.lit(1))
    members = assigned.where("cluster_id >= 0").join(kept, ["graph_id", "cluster_id"], "left")
    lost = F.count(F.when(F.col("kept").isNull(), 1))
    return members.groupBy("cluster_id").agg(lost.alias("n_unsupported"), F.round(lost / F.count(F.lit(1)), 6).alias("share"))


@query(f"WITH {PROBE} SELECT count(*) AS n_violations FROM asg a WHERE c > 0 AND NOT EXISTS (SELECT 1 FROM hits h WHERE h.g = a.g AND h.c = a.c)")
def order_invariant_violations(spark, sf):
    assigned, hits = _both(spark, sf)
    return assigned.where("cluster_id >= 0").join(hits, ["graph_id", "cluster_id"], "left_anti").agg(F.count(F.lit(1)).alias("n_violations"))


@query(f"WITH {PROBE} SELECT alpha, round((SELECT sum(n * hcov) FROM hc) / (SELECT count(*) FROM hc) ** alpha, 6) AS z FROM (SELECT unnest([0.5, 1.0, 2.0])::DOUBLE AS alpha)")
def order_objective(spark, sf):
    return probe.objective(probe.hcov(_assigned(spark, sf), _reps(spark)), (0.5, 1, 2)).select("alpha", F.round("z", 6).alias("z"))


@query(f"""WITH {PROBE}, k AS (SELECT c, rep, rsize, CASE WHEN rep = 3 THEN 3 ELSE 1 END AS own FROM rk WHERE n_sup_c > 0),
s AS (SELECT a.c AS c1, b.c AS c2, (CASE WHEN a.rep = b.rep THEN a.own ELSE 0 END) / greatest(a.rsize, b.rsize)::DOUBLE AS sim FROM k a JOIN k b ON a.c < b.c)
SELECT c1, c2, count(*) FILTER (WHERE sim >= 0.3) AS n_similar, count(*) FILTER (WHERE sim >= 0.3) >= 3 AS merged FROM s GROUP BY c1, c2""")
def merge_pairs(spark, sf):
    """Pairs of clusters of the order graphs, by those representatives that their members support."""
    return probe.merge_pairs(probe.region_probes(), _ranked(spark, sf))


def _months(spark, sf):
    m = table(spark, sf, "orders").groupBy(F.trunc("o_orderdate", "month").alias("m")).agg(F.sum(F.col("o_totalprice").cast("decimal(18,2)")).cast("double").alias("z"))
    return m.select(F.row_number().over(Window.orderBy("m")).cast("bigint").alias("i"), "z")


@query("""WITH m AS (SELECT date_trunc('month', o_orderdate) AS m, sum(o_totalprice::DECIMAL(18,2))::DOUBLE AS z FROM orders GROUP BY 1),
i AS (SELECT row_number() OVER (ORDER BY m) AS i, z FROM m), s AS (SELECT *, sum(z) OVER (ORDER BY i ROWS BETWEEN 2 PRECEDING AND CURRENT ROW) AS w FROM i),
r AS (SELECT i, z, w / lag(w, 3) OVER (ORDER BY i) AS ratio FROM s)
SELECT i, round(z, 2) AS z, round(ratio, 6) AS ratio, ratio <= 1.01 AS stop FROM r WHERE i >= 6""")
def smoothed_stop(spark, sf):
    return probe.stop_series(_months(spark, sf)).select("i", F.round("z", 2).alias("z"), F.round("ratio", 6).alias("ratio"), "stop")


LEVELS = """lv AS (SELECT level::INTEGER AS level, (30 * (1 << level))::BIGINT AS n FROM (SELECT unnest(range(0, 40)) AS level) WHERE 30 * (1::BIGINT << level) < (SELECT count(*) FROM og)),
sr AS (SELECT og.g, row_number() OVER (ORDER BY md5(og.g || ':7')) AS k, h.g IS NOT NULL AS hit FROM og LEFT JOIN (SELECT g FROM hits WHERE c = 3 AND rep = 1) h ON og.g = h.g),
lh AS (SELECT level, n, (SELECT count(*) FROM sr WHERE k <= n AND hit) AS k_hits FROM lv)"""
BOUND = FREQUENT_PATHS + """, dbl AS (SELECT count(*) AS d FROM (SELECT unnest(range(0, 40)) AS j) WHERE 30 * (1::BIGINT << j) < (SELECT count(*) FROM og)),
vq AS (SELECT 0.4::DOUBLE AS minsup, quantile_disc(n_v, 0.6) AS vmax FROM og UNION ALL SELECT 0.9, quantile_disc(n_v, 0.1) FROM og UNION ALL SELECT 0.99, quantile_disc(n_v, 0.01) FROM og),
tb AS (SELECT minsup, d AS doublings, (SELECT count(*) FROM fp) AS n_paths, d * (vmax * vmax + vmax) * (SELECT count(*) FROM fp) AS bound FROM vq, dbl)"""


@query(f"WITH {PROBE}, {LEVELS} SELECT level, n, k_hits FROM lh")
def sample_levels(spark, sf):
    return gs.sample_levels(_graphs(spark, sf), has_edge("STANDARD", "O", "ASIA"))


@query(f"WITH {PROBE}, {BOUND} SELECT minsup, vmax::BIGINT AS vmax FROM vq")
def vmax_quantile(spark, sf):
    return gs.vmax_quantile(_graphs(spark, sf), (0.4, 0.9, 0.99))


def _bound(spark, sf):
    g = _graphs(spark, sf)
    levels, paths = gs.doublings(g.count()), gs.frequent_paths(g, 0.045).agg(F.count(F.lit(1)).alias("n_paths"))
    v = gs.vmax_quantile(g, (0.4, 0.9, 0.99)).crossJoin(F.broadcast(paths))
    return v.select("minsup", F.lit(levels).cast("bigint").alias("doublings"), "n_paths", (F.lit(levels) * (F.col("vmax") * F.col("vmax") + F.col("vmax")) * F.col("n_paths")).cast("bigint").alias("bound"))


@query(f"WITH {PROBE}, {BOUND} SELECT minsup, doublings, n_paths, bound::BIGINT AS bound, round(0.5 / bound * 1e6, 6) AS alpha_millionths FROM tb")
def test_bound(spark, sf):
    return _bound(spark, sf).withColumn("alpha_millionths", F.round(0.5 / F.col("bound") * 1e6, 6))


@query(f"""WITH {PROBE}, {LEVELS}, {BOUND}, a AS (SELECT 0.5 / bound AS alpha FROM tb WHERE minsup = 0.9), q AS (SELECT lh.*, m.minsup FROM lh, (SELECT unnest([0.05, 0.09])::DOUBLE AS minsup) m),
tails AS (SELECT minsup, level, n, k_hits, sum(CASE WHEN i <= k_hits THEN p ELSE 0 END) AS low, sum(CASE WHEN i >= k_hits THEN p ELSE 0 END) AS high FROM (
  SELECT q.*, i, exp(lgamma(n + 1) - lgamma(i + 1) - lgamma(n - i + 1) + i * ln(minsup) + (n - i) * ln(1 - minsup)) AS p FROM q, (SELECT unnest(range(0, 20000)) AS i) WHERE i <= n) GROUP BY ALL)
SELECT minsup, level, n, k_hits, CASE WHEN k_hits / n::DOUBLE < minsup AND low < (SELECT alpha FROM a) THEN 'INFREQUENT' WHEN k_hits / n::DOUBLE >= minsup AND high < (SELECT alpha FROM a) THEN 'FREQUENT' ELSE 'UNDECIDED' END AS decision FROM tails""")
def binomial_decisions(spark, sf):
    levels = gs.sample_levels(_graphs(spark, sf), has_edge("STANDARD", "O", "ASIA"))
    alpha = _bound(spark, sf).where("minsup = 0.9").select((0.5 / F.col("bound")).alias("alpha"))
    asked = levels.crossJoin(F.broadcast(alpha)).select("*", F.explode(F.array(F.lit(0.05), F.lit(0.09))).alias("minsup"))
    return asked.select("minsup", "level", "n", "k_hits", decision_column("k_hits", "n", "minsup", "alpha").alias("decision"))


def _guess(spark, sf):
    """Documents by the language whose function words they use most."""
    d = table(spark, sf, "documents")
    words = F.regexp_extract_all(F.lower("text"), F.lit(r"(\p{L}+)"), 1)
    count = lambda own: F.size(F.filter("w", lambda x: x.isin(own)))
    scores = F.array(*[F.struct(count(own).alias("n"), F.lit(-i).alias("minus"), F.lit(lang).alias("lang")) for i, (lang, own) in enumerate(corpora.GUESS_WORDS.items())])
    best = F.array_max("scores")
    return d.select("doc_id", "lang", words.alias("w")).select("doc_id", "lang", scores.alias("scores")).select("doc_id", "lang", F.when(best["n"] > 0, -best["minus"]).otherwise(F.lit(-1)).alias("cluster_id"))


_counts = ", ".join("len(list_filter(w, lambda x: x IN (" + ", ".join(f"'{w}'" for w in own) + f"))) AS n{i}" for i, own in enumerate(corpora.GUESS_WORDS.values()))
GUESS = rf"""gw AS (SELECT doc_id, lang, regexp_extract_all(lower(text), '(\p{{L}}+)', 1) AS w FROM documents), gn AS (SELECT doc_id, lang, {_counts} FROM gw),
gc AS (SELECT doc_id, lang, CASE WHEN greatest(n0, n1, n2, n3) = 0 THEN -1 WHEN n0 = greatest(n0, n1, n2, n3) THEN 0 WHEN n1 = greatest(n0, n1, n2, n3) THEN 1 WHEN n2 = greatest(n0, n1, n2, n3) THEN 2 ELSE 3 END AS cluster_id FROM gn),
ct AS (SELECT cluster_id, lang, count(*) AS n FROM gc GROUP BY cluster_id, lang)"""


def _contingency(spark, sf):
    return measures.contingency(_guess(spark, sf), "cluster_id", "lang")


@query(f"WITH {GUESS} SELECT cluster_id, lang, n FROM ct")
def doc_contingency(spark, sf):
    return _contingency(spark, sf)


@query(f"""WITH {GUESS}, t AS (SELECT sum(n)::DOUBLE AS t FROM ct), h AS (
  SELECT (SELECT -sum(n / t * log2(n / t)) FROM ct, t) AS hj, (SELECT -sum(n / t * log2(n / t)) FROM (SELECT sum(n) AS n FROM ct GROUP BY cluster_id), t) AS ha, (SELECT -sum(n / t * log2(n / t)) FROM (SELECT sum(n) AS n FROM ct GROUP BY lang), t) AS hb)
SELECT round(2 * hj - ha - hb, 6) AS vi, round((2 * hj - ha - hb) / hj, 6) AS nvi_dist, round(1 - (2 * hj - ha - hb) / hj, 6) AS nvi FROM h""")
def doc_nvi(spark, sf):
    return measures.nvi(_contingency(spark, sf))


@query(f"""WITH {GUESS} SELECT round((SELECT sum(n::DOUBLE * (n - 1) / 2) FROM ct) / sqrt((SELECT sum(n::DOUBLE * (n - 1) / 2) FROM (SELECT sum(n) AS n FROM ct GROUP BY cluster_id)) * (SELECT sum(n::DOUBLE * (n - 1) / 2) FROM (SELECT sum(n) AS n FROM ct GROUP BY lang))), 6) AS fm""")
def doc_fm(spark, sf):
    return measures.fowlkes_mallows(_contingency(spark, sf))


@query(f"WITH {GUESS} SELECT round((SELECT sum(m) FROM (SELECT max(n) AS m FROM ct GROUP BY cluster_id)) / (SELECT sum(n) FROM ct)::DOUBLE, 6) AS purity")
def doc_purity(spark, sf):
    return measures.purity(_contingency(spark, sf))


@query(f"WITH {GUESS} SELECT cluster_id, lang, count(*) AS n FROM gc GROUP BY CUBE (cluster_id, lang)")
def doc_rollup(spark, sf):
    return _guess(spark, sf).cube("cluster_id", "lang").agg(F.count(F.lit(1)).alias("n"))


THREE = """arcs AS (SELECT g, a AS m, b AS o, l FROM {e} UNION ALL SELECT g, b, a, l FROM {e}), lab AS (SELECT g, v, l FROM {v}),
pr AS (SELECT p.g, p.m, p.o AS x, p.l AS lx, q.o AS y, q.l AS ly FROM arcs p JOIN arcs q ON p.g = q.g AND p.m = q.m AND p.o < q.o),
tr AS (SELECT pr.*, c.l AS lc, lm.l AS vm, vx.l AS vx, vy.l AS vy FROM pr LEFT JOIN arcs c ON c.g = pr.g AND c.m = pr.x AND c.o = pr.y
       JOIN lab lm ON lm.g = pr.g AND lm.v = pr.m JOIN lab vx ON vx.g = pr.g AND vx.v = x JOIN lab vy ON vy.g = pr.g AND vy.v = y),
f3 AS (SELECT g, CASE WHEN lc IS NULL THEN 'P/' || vm || '/' || least(lx || ':' || vx, ly || ':' || vy) || '/' || greatest(lx || ':' || vx, ly || ':' || vy)
                 ELSE 'T/' || array_to_string(list_sort([vm || ':' || lc, vx || ':' || ly, vy || ':' || lx]), '/') END AS feature FROM tr WHERE lc IS NULL OR m < x)"""


@query(f"WITH {SESSION}, {THREE.format(v='sv', e='se')} SELECT feature, count(*) AS n_occurrences, count(DISTINCT g) AS n_graphs FROM f3 GROUP BY feature")
def session_three_vertex(spark, sf):
    f = gs.three_vertex_features(_graphs(spark, sf, "session"))
    return f.groupBy("feature").agg(F.sum("cnt").cast("bigint").alias("n_occurrences"), F.count(F.lit(1)).alias("n_graphs"))


@query(f"WITH {ORDER}, {THREE.format(v='ov', e='oe')} SELECT count(DISTINCT feature) AS dim FROM f3")
def order_feature_dim(spark, sf):
    return gs.three_vertex_features(_graphs(spark, sf)).agg(F.countDistinct("feature").alias("dim"))


WL = """arcs AS (SELECT g, a AS m, b AS o, l FROM {e} UNION ALL SELECT g, b, a, l FROM {e}),
near AS (SELECT x.g, x.m, array_to_string(list_sort(list(x.l || ':' || y.l)), ',') AS s FROM arcs x JOIN {v} y ON x.g = y.g AND x.o = y.v GROUP BY x.g, x.m)
SELECT md5(v.l || '|' || coalesce(near.s, '')) AS wl, count(*) AS n FROM {v} v LEFT JOIN near ON near.g = v.g AND near.m = v.v GROUP BY 1"""


@query(f"WITH {ORDER}, {WL.format(v='ov', e='oe')}")
def order_wl1(spark, sf):
    return gs.wl_histogram(_graphs(spark, sf))


@query(f"WITH {SESSION}, {WL.format(v='sv', e='se')}")
def session_wl1(spark, sf):
    return gs.wl_histogram(_graphs(spark, sf, "session"))


@query(f"""WITH {SESSION}, arcs AS (SELECT g, a AS m, b AS o, l FROM se UNION ALL SELECT g, b, a, l FROM se)
SELECT x.l || '/' || p.l || '/' || y.l || '/' || q.l || '/' || z.l AS walk, count(*) AS n FROM arcs p JOIN arcs q ON p.g = q.g AND p.o = q.m
JOIN sv x ON x.g = p.g AND x.v = p.m JOIN sv y ON y.g = p.g AND y.v = p.o JOIN sv z ON z.g = q.g AND z.v = q.o GROUP BY 1""")
def session_walk2(spark, sf):
    return gs.walk_features(_graphs(spark, sf, "session"))


@query(f"WITH {PROBE} SELECT g FROM hits WHERE c = 3 AND rep = 3")
def order_search(spark, sf):
    """Graphs that contain a path of two edges: fingerprints first, an exact test of what they leave."""
    query_graph = Graph.of(["5-LOW", "MEDIUM", "ASIA"], [0, 1], [1, 2], ["R", "O"])
    return scan.search(with_fingerprint(_graphs(spark, sf)), query_graph).select(F.col("graph_id").alias("g"))


@query(f"""WITH {PROBE}, f AS (SELECT c, (SELECT count(*) FROM (SELECT g FROM ot WHERE la = '5-LOW' AND le = 'R' AND lb = 'MEDIUM' INTERSECT SELECT g FROM ot WHERE la = 'MEDIUM' AND le = 'O' AND lb = r)) AS k,
  (SELECT count(*) FROM hits WHERE hits.c = reg.c AND rep = 3) AS h FROM reg)
SELECT c AS cluster_id, k AS n_candidates, h AS n_hits, round(h / k::DOUBLE, 6) AS precision FROM f""")
def fingerprint_filter_power(spark, sf):
    g = _graphs(spark, sf).withColumn("keys", triple_keys())
    key = lambda e: "|".join((min(e[0], e[2]), e[1], max(e[0], e[2])))
    flags = F.array(*[
        F.struct(F.lit(p.cluster_id).alias("c"), (F.array_contains("keys", key(p.edges[0])) & F.array_contains("keys", key(p.edges[1]))).alias("may"), p.hit.alias("hit"))
        for p in probe.region_probes() if p.rep_id == 3
    ])
    x = g.select(F.explode(flags).alias("x"))
    may, hit = F.count(F.when(F.col("x.may"), 1)), F.count(F.when(F.col("x.may") & F.col("x.hit"), 1))
    return x.groupBy(F.col("x.c").alias("cluster_id")).agg(may.alias("n_candidates"), hit.alias("n_hits"), F.round(hit / may, 6).alias("precision"))


@query()
def fingerprint_power(spark, sf):
    """``(cluster_id, n_candidates, n_hits, precision)`` of the 1,024-bit fingerprint; its hash has no SQL, hits must be those of ``fingerprint_filter_power``."""
    g = with_fingerprint(_graphs(spark, sf))
    probes = [p for p in probe.region_probes() if p.rep_id == 3]
    mark = lambda p: fingerprint(Graph.of(["5-LOW", "MEDIUM", p.edges[1][2]], [0, 1], [1, 2], ["R", "O"]))
    flags = F.array(*[F.struct(F.lit(p.cluster_id).alias("c"), may_contain(F.col("fp"), mark(p)).alias("may"), p.hit.alias("hit")) for p in probes])
    x = g.select(F.explode(flags).alias("x"))
    may, hit = F.count(F.when(F.col("x.may"), 1)), F.count(F.when(F.col("x.may") & F.col("x.hit"), 1))
    return x.groupBy(F.col("x.c").alias("cluster_id")).agg(may.alias("n_candidates"), hit.alias("n_hits"), F.round(hit / may, 6).alias("precision"))


@query("""WITH k AS (SELECT ('0x' || substr(md5(o_orderkey || ':class'), 1, 7))::BIGINT % 100 AS class FROM orders WHERE ('0x' || substr(md5(o_orderkey || ':noise'), 1, 7))::BIGINT % 20 <> 0)
SELECT class, count(*) AS n FROM k GROUP BY class""")
def planted_class_sizes(spark, sf):
    return planted_truth(table(spark, sf, "orders")).where("NOT noise").groupBy("class").agg(F.count(F.lit(1)).alias("n"))


@query(f"""WITH {PROBE}, m AS (SELECT h.c, ('0x' || substr(md5(h.g || ':class'), 1, 7))::BIGINT % 100 AS class FROM (SELECT DISTINCT g, c FROM hits) h), k AS (SELECT c, class, count(*) AS n FROM m GROUP BY c, class)
SELECT round((SELECT sum(x) FROM (SELECT max(n) AS x FROM k GROUP BY c)) / (SELECT sum(n) FROM k)::DOUBLE, 6) AS purity""")
def overlap_purity_probe(spark, sf):
    members = _hits(spark, sf).select("graph_id", "cluster_id").distinct()
    truth = planted_truth(table(spark, sf, "orders")).select("graph_id", "class")
    return measures.purity(measures.contingency(members.join(truth, "graph_id"), "cluster_id", "class"))


EMB = "em AS (SELECT vec_id, label, list_transform(embedding, lambda x: x::DOUBLE) AS v FROM embeddings)"


MEDOIDS = "m AS (SELECT vec_id AS medoid, v FROM (SELECT *, row_number() OVER (PARTITION BY label ORDER BY vec_id) AS k FROM em) WHERE k = 1)"


@query(f"""WITH {EMB}, {MEDOIDS}, d AS (SELECT sqrt(list_sum(list_transform(list_zip(x.v, y.v), lambda p: (p[1] - p[2]) * (p[1] - p[2])))) AS d FROM em x JOIN m y ON x.vec_id <> y.medoid)
SELECT round(avg(d), 6) AS mean_d, round(stddev_pop(d), 6) AS sd_d, round(avg(d) * avg(d) / (2 * var_pop(d)), 6) AS rho, round((max(d) - min(d)) / min(d), 6) AS contrast FROM d""")
def embedding_concentration(spark, sf):
    return vectors.concentration(vectors.doubles(table(spark, sf, "embeddings")))


@query(f"""WITH {EMB}, {MEDOIDS},
d AS (SELECT e.vec_id, m.medoid, list_sum(list_transform(list_zip(e.v[1:20], m.v[1:20]), lambda p: abs(p[1] - p[2]))) / 20 AS dist FROM em e, m)
SELECT vec_id, medoid, round(dist, 6) AS dist FROM (SELECT *, row_number() OVER (PARTITION BY vec_id ORDER BY round(dist, 9), medoid) AS k FROM d) WHERE k = 1""")
def segmental_assign_embeddings(spark, sf):
    e = vectors.doubles(table(spark, sf, "embeddings"))
    return vectors.segmental_assign(e, vectors.label_medoids(e), 20)


@query(f"WITH {EMB}, {MEDOIDS} SELECT m.medoid AS i, e.vec_id AS j, round(list_sum(list_transform(list_zip(m.v, e.v), lambda p: p[1] * p[2])), 6) AS k FROM em e, m")
def kernel_gram_block(spark, sf):
    return vectors.gram_block(vectors.doubles(table(spark, sf, "embeddings")))


@query(f"""WITH {EMB}, u AS (SELECT vec_id % 10 AS c, unnest(v) AS x, unnest(range(0, len(v))) AS j FROM em), a AS (SELECT c, j, avg(x) AS x FROM u GROUP BY c, j),
mean AS (SELECT c, list(x ORDER BY j) AS mv FROM a GROUP BY c), d AS (SELECT vec_id, c, list_sum(list_transform(mv, lambda x: x * x)) - 2 * list_sum(list_transform(list_zip(v, mv), lambda p: p[1] * p[2])) AS d FROM em, mean)
SELECT vec_id, c::BIGINT AS cluster FROM (SELECT *, row_number() OVER (PARTITION BY vec_id ORDER BY round(d, 9), c) AS r FROM d) WHERE r = 1""")
def kernel_assign_step(spark, sf):
    e = vectors.doubles(table(spark, sf, "embeddings"))
    return vectors.kernel_step(e.withColumn("cluster", F.col("vec_id") % 10))


@query("""WITH m AS (SELECT o_orderpriority, date_trunc('month', o_orderdate) AS m, sum(o_totalprice::DECIMAL(18,2))::DOUBLE AS s FROM orders GROUP BY 1, 2)
SELECT o_orderpriority, round(avg(s), 4) AS mean, round(stddev_samp(s) / avg(s), 6) AS cv FROM m GROUP BY 1""")
def runs_cv(spark, sf):
    runs = table(spark, sf, "orders").groupBy("o_orderpriority", F.trunc("o_orderdate", "month").alias("m")).agg(F.sum(F.col("o_totalprice").cast("decimal(18,2)")).cast("double").alias("s"))
    return measures.cv(runs, "o_orderpriority", "s").withColumn("mean", F.round("mean", 4))
