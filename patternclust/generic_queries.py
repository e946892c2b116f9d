"""The relational operators around the methods, one query each, with SQL."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .functions.patterns import has_edge
from .model import with_size
from .queries import GUESS, ORDER, PROBE, _graphs, _guess, query
from .sources.tables import table


@query("SELECT l_orderkey, l_partkey, l_extendedprice FROM lineitem WHERE l_quantity >= 45 AND l_returnflag = 'R'")
def op_scan_project_filter(spark, sf):
    return table(spark, sf, "lineitem").where("l_quantity >= 45 AND l_returnflag = 'R'").select("l_orderkey", "l_partkey", "l_extendedprice")


@query("SELECT p_type, count(*) AS n, sum(l_quantity)::DOUBLE AS quantity FROM lineitem JOIN part ON l_partkey = p_partkey GROUP BY p_type")
def op_hash_join(spark, sf):
    # the dimension's size is left to the planner, which broadcasts under its threshold only
    joined = table(spark, sf, "lineitem").select("l_partkey", "l_quantity").join(table(spark, sf, "part").select("p_partkey", "p_type"), F.col("l_partkey") == F.col("p_partkey"))
    return joined.groupBy("p_type").agg(F.count(F.lit(1)).alias("n"), F.sum("l_quantity").alias("quantity"))


@query("SELECT o_orderkey, o_orderpriority, count(*) AS n_lines FROM orders JOIN lineitem ON o_orderkey = l_orderkey GROUP BY o_orderkey, o_orderpriority")
def op_sort_merge_join(spark, sf):
    o, li = table(spark, sf, "orders").select("o_orderkey", "o_orderpriority"), table(spark, sf, "lineitem").select("l_orderkey")
    return o.hint("merge").join(li, F.col("o_orderkey") == F.col("l_orderkey")).groupBy("o_orderkey", "o_orderpriority").agg(F.count(F.lit(1)).alias("n_lines"))


@query("SELECT n_name, r_name FROM nation, region WHERE length(n_name) / length(r_name)::DOUBLE >= 1.2")
def op_nested_loop_join(spark, sf):
    return table(spark, sf, "nation").join(table(spark, sf, "region"), F.length("n_name") / F.length("r_name") >= 1.2).select("n_name", "r_name")


@query(f"WITH {ORDER} SELECT rsize, count(*) AS n FROM og JOIN (SELECT unnest([3, 9, 15, 21, 40]) AS rsize) r ON rsize <= gsize GROUP BY rsize")
def op_range_join(spark, sf):
    sizes = with_size(_graphs(spark, sf)).groupBy("gsize").count()  # few rows before the inequality
    asked = spark.createDataFrame([(3,), (9,), (15,), (21,), (40,)], "rsize int")
    return asked.join(sizes, F.col("rsize") <= F.col("gsize")).groupBy("rsize").agg(F.sum("count").alias("n"))


@query("""SELECT p.event_id, max_by(v.event_id, (v.ts, v.event_id)) AS view_id FROM events p LEFT JOIN events v ON v.user_id = p.user_id AND v.event_type = 'view' AND (v.ts < p.ts OR (v.ts = p.ts AND v.event_id < p.event_id))
WHERE p.event_type = 'purchase' GROUP BY p.event_id""")
def op_asof_join(spark, sf):
    e = table(spark, sf, "events").where(F.col("event_type").isin("view", "purchase")).select("event_id", "user_id", "ts", "event_type")
    w = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, -1)
    last = F.last(F.when(F.col("event_type") == "view", F.col("event_id")), ignorenulls=True).over(w)
    return e.withColumn("view_id", last).where("event_type = 'purchase'").select("event_id", "view_id")


@query("""SELECT c.event_id AS click_id, p.event_id AS purchase_id FROM events c JOIN events p ON c.user_id = p.user_id AND c.event_type = 'click' AND p.event_type = 'purchase'
AND p.ts >= c.ts AND p.ts <= c.ts + INTERVAL 30 MINUTE""")
def op_interval_join(spark, sf):
    e = table(spark, sf, "events").select("event_id", "user_id", "ts", "event_type")
    slot = F.window("ts", "30 minutes")["start"]
    c = e.where("event_type = 'click'").select(F.col("event_id").alias("click_id"), "user_id", F.col("ts").alias("from"), slot.alias("s"))
    # a partner lies in the same half hour or the next: equality on (user, slot) instead of on the user alone
    c = c.select("click_id", "user_id", "from", F.explode(F.array(F.col("s"), F.col("s") + F.expr("INTERVAL 30 MINUTES"))).alias("s"))
    p = e.where("event_type = 'purchase'").select(F.col("event_id").alias("purchase_id"), "user_id", F.col("ts").alias("to"), slot.alias("s"))
    return c.join(p, ["user_id", "s"]).where((F.col("to") >= F.col("from")) & (F.col("to") <= F.col("from") + F.expr("INTERVAL 30 MINUTES"))).select("click_id", "purchase_id")


@query("SELECT o_orderkey FROM orders WHERE o_orderkey IN (SELECT l_orderkey FROM lineitem)")
def op_semi_join(spark, sf):
    return table(spark, sf, "orders").select("o_orderkey").join(table(spark, sf, "lineitem"), F.col("o_orderkey") == F.col("l_orderkey"), "left_semi")


@query("SELECT o_orderkey FROM orders WHERE o_orderkey NOT IN (SELECT l_orderkey FROM lineitem)")
def op_anti_join(spark, sf):
    return table(spark, sf, "orders").select("o_orderkey").join(table(spark, sf, "lineitem"), F.col("o_orderkey") == F.col("l_orderkey"), "left_anti")


@query("SELECT coalesce(d.doc_id, l.doc_id) AS doc_id, d.lang, l.quality FROM documents d FULL JOIN labels l ON d.doc_id = l.doc_id")
def op_outer_join(spark, sf):
    d, labels = table(spark, sf, "documents").select("doc_id", "lang"), table(spark, sf, "labels").select("doc_id", "quality")
    return d.join(labels, "doc_id", "full_outer")


def _order_vertices(spark, sf):
    return _graphs(spark, sf).select("graph_id", F.explode("vl").alias("l"))


@query(f"WITH {ORDER} SELECT l, count(*) AS n FROM ov GROUP BY l")
def op_group_agg(spark, sf):
    return _order_vertices(spark, sf).groupBy("l").agg(F.count(F.lit(1)).alias("n"))


@query(f"WITH {ORDER} SELECT l, count(DISTINCT g) AS n_graphs FROM ov GROUP BY l")
def op_distinct_agg(spark, sf):
    return _order_vertices(spark, sf).groupBy("l").agg(F.countDistinct("graph_id").alias("n_graphs"))


@query("SELECT o_orderpriority, o_orderstatus, count(*) AS n FROM orders GROUP BY ROLLUP (o_orderpriority, o_orderstatus)")
def op_rollup(spark, sf):
    return table(spark, sf, "orders").rollup("o_orderpriority", "o_orderstatus").agg(F.count(F.lit(1)).alias("n"))


@query("SELECT o_orderpriority, o_orderstatus, count(*) AS n FROM orders GROUP BY CUBE (o_orderpriority, o_orderstatus)")
def op_cube(spark, sf):
    return table(spark, sf, "orders").cube("o_orderpriority", "o_orderstatus").agg(F.count(F.lit(1)).alias("n"))


@query("SELECT o_orderpriority, o_orderstatus, count(*) AS n FROM orders GROUP BY GROUPING SETS ((o_orderpriority), (o_orderstatus), ())")
def op_grouping_sets(spark, sf):
    sets = [[F.col("o_orderpriority")], [F.col("o_orderstatus")], []]
    return table(spark, sf, "orders").groupingSets(sets, "o_orderpriority", "o_orderstatus").agg(F.count(F.lit(1)).alias("n"))


@query(f"WITH {GUESS} SELECT cluster_id, count(*) FILTER (WHERE lang = 'en') AS en, count(*) FILTER (WHERE lang = 'fr') AS fr, count(*) FILTER (WHERE lang = 'de') AS de, count(*) FILTER (WHERE lang = 'es') AS es FROM gc GROUP BY cluster_id")
def op_pivot(spark, sf):
    return _guess(spark, sf).groupBy("cluster_id").pivot("lang", ["en", "fr", "de", "es"]).agg(F.count(F.lit(1))).na.fill(0, ["en", "fr", "de", "es"])


@query("""SELECT o_orderkey, rank() OVER w AS r, dense_rank() OVER w AS d, row_number() OVER (PARTITION BY o_custkey ORDER BY o_totalprice DESC, o_orderkey) AS n, ntile(4) OVER (PARTITION BY o_custkey ORDER BY o_totalprice DESC, o_orderkey) AS q
FROM orders WINDOW w AS (PARTITION BY o_custkey ORDER BY o_orderpriority)""")
def op_window_rank(spark, sf):
    w = Window.partitionBy("o_custkey").orderBy("o_orderpriority")
    v = Window.partitionBy("o_custkey").orderBy(F.col("o_totalprice").desc(), "o_orderkey")
    ranks = [f.over(x).cast("bigint").alias(n) for n, f, x in (("r", F.rank(), w), ("d", F.dense_rank(), w), ("n", F.row_number(), v), ("q", F.ntile(4), v))]
    return table(spark, sf, "orders").select("o_orderkey", *ranks)


@query("""SELECT o_orderkey, count(*) OVER (PARTITION BY o_custkey ORDER BY o_orderkey ROWS BETWEEN 2 PRECEDING AND CURRENT ROW) AS n3,
max(o_orderkey) OVER (PARTITION BY o_custkey ORDER BY o_orderkey RANGE BETWEEN 1000 PRECEDING AND 1 PRECEDING) AS near FROM orders""")
def op_window_frame(spark, sf):
    w = Window.partitionBy("o_custkey").orderBy("o_orderkey")
    return table(spark, sf, "orders").select("o_orderkey", F.count(F.lit(1)).over(w.rowsBetween(-2, 0)).alias("n3"), F.max("o_orderkey").over(w.rangeBetween(-1000, -1)).alias("near"))


@query("SELECT event_id, lag(event_type) OVER w AS before, lead(event_type) OVER w AS after, first_value(event_type) OVER w AS first FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)")
def op_window_lag(spark, sf):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    return table(spark, sf, "events").select("event_id", F.lag("event_type").over(w).alias("before"), F.lead("event_type").over(w).alias("after"), F.first("event_type").over(w).alias("first"))


@query("SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 20")
def op_topk(spark, sf):
    return table(spark, sf, "orders").select("o_orderkey", "o_totalprice").orderBy(F.col("o_totalprice").desc(), "o_orderkey").limit(20)


@query("SELECT o_orderpriority, o_orderkey, k FROM (SELECT *, row_number() OVER (PARTITION BY o_orderpriority ORDER BY o_totalprice DESC, o_orderkey) AS k FROM orders) WHERE k <= 3")
def op_topk_per_group(spark, sf):
    w = Window.partitionBy("o_orderpriority").orderBy(F.col("o_totalprice").desc(), "o_orderkey")
    return table(spark, sf, "orders").withColumn("k", F.row_number().over(w).cast("bigint")).where("k <= 3").select("o_orderpriority", "o_orderkey", "k")


_ASIA, _EUROPE = ("STANDARD", "O", "ASIA"), ("STANDARD", "O", "EUROPE")


def _supporters(spark, sf, edge):
    return _graphs(spark, sf).where(has_edge(*edge)).select(F.col("graph_id").alias("g"))


for _name, _op, _combine in (("union", "UNION", lambda a, b: a.union(b).distinct()), ("intersect", "INTERSECT", lambda a, b: a.intersect(b)), ("except", "EXCEPT", lambda a, b: a.exceptAll(b))):
    query(f"WITH {PROBE} SELECT g FROM hits WHERE c = 3 AND rep = 1 {_op} SELECT g FROM hits WHERE c = 4 AND rep = 1", f"op_{_name}")(
        lambda spark, sf, _combine=_combine: _combine(_supporters(spark, sf, _ASIA), _supporters(spark, sf, _EUROPE))
    )


@query("""SELECT doc_id, md5(text) AS digest, upper(lang) AS lang, length(source) AS n_source, substr(text, 1, 10) AS head, split_part(source, 'c', 2) AS tail, replace(source, 'src', 's') AS short FROM documents""")
def op_string(spark, sf):
    t = table(spark, sf, "documents")
    return t.select("doc_id", F.md5("text").alias("digest"), F.upper("lang").alias("lang"), F.length("source").cast("bigint").alias("n_source"), F.substring("text", 1, 10).alias("head"), F.split_part("source", F.lit("c"), F.lit(2)).alias("tail"), F.replace("source", F.lit("src"), F.lit("s")).alias("short"))


@query("SELECT o_orderkey, year(o_orderdate) AS y, month(o_orderdate) AS m, week(o_orderdate) AS w, strftime(date_trunc('quarter', o_orderdate), '%Y-%m-%d') AS q, datediff('day', TIMESTAMP '1992-01-01', o_orderdate) AS days FROM orders")
def op_date(spark, sf):
    d = F.col("o_orderdate")
    return table(spark, sf, "orders").select("o_orderkey", *[f(d).cast("bigint").alias(n) for n, f in (("y", F.year), ("m", F.month), ("w", F.weekofyear))], F.date_format(F.date_trunc("quarter", d), "yyyy-MM-dd").alias("q"), F.datediff(d, F.lit("1992-01-01").cast("date")).cast("bigint").alias("days"))


@query("SELECT o_orderkey, round(ln(o_totalprice), 6) AS l, round(sqrt(o_totalprice), 6) AS s, ceil(o_totalprice)::BIGINT AS c, floor(o_totalprice)::BIGINT AS f, round(o_totalprice ** 0.25, 6) AS p, o_orderkey % 7 AS r FROM orders")
def op_math(spark, sf):
    p = F.col("o_totalprice")
    return table(spark, sf, "orders").select("o_orderkey", F.round(F.ln(p), 6).alias("l"), F.round(F.sqrt(p), 6).alias("s"), F.ceil(p).alias("c"), F.floor(p).alias("f"), F.round(F.pow(p, F.lit(0.25)), 6).alias("p"), (F.col("o_orderkey") % 7).alias("r"))


@query("""SELECT vec_id, len(embedding) AS n, round(list_sum(list_transform(embedding, lambda x: x::DOUBLE * x::DOUBLE)), 6) AS sq, len(list_filter(embedding, lambda x: x > 0)) AS pos, round(list_max(embedding)::DOUBLE, 6) AS top FROM embeddings""")
def op_array(spark, sf):
    v = F.col("embedding").cast("array<double>")
    return table(spark, sf, "embeddings").select("vec_id", F.size(v).cast("bigint").alias("n"), F.round(F.aggregate(v, F.lit(0.0), lambda s, x: s + x * x), 6).alias("sq"), F.size(F.filter(v, lambda x: x > 0)).cast("bigint").alias("pos"), F.round(F.array_max(v), 6).alias("top"))


@query("""WITH c AS (SELECT user_id, event_type, count(*) AS n FROM events GROUP BY user_id, event_type) SELECT user_id, sum(n)::BIGINT AS total, max(CASE WHEN event_type = 'view' THEN n END) AS views, count(*) AS kinds FROM c GROUP BY user_id""")
def op_map(spark, sf):
    counts = table(spark, sf, "events").groupBy("user_id", "event_type").agg(F.count(F.lit(1)).alias("n"))
    m = counts.groupBy("user_id").agg(F.map_from_entries(F.collect_list(F.struct("event_type", "n"))).alias("m"))
    return m.select("user_id", F.aggregate(F.map_values("m"), F.lit(0).cast("bigint"), lambda s, x: s + x).alias("total"), F.try_element_at("m", F.lit("view")).alias("views"), F.size("m").cast("bigint").alias("kinds"))


@query("SELECT event_id, (props ->> '$.k')::BIGINT AS k FROM events")
def op_json(spark, sf):
    return table(spark, sf, "events").select("event_id", F.from_json("props", "k bigint")["k"].alias("k"))


@query("SELECT l_returnflag, round(quantile_cont(l_extendedprice, 0.5), 4) AS median, quantile_disc(l_quantity, 0.9) AS q90 FROM lineitem GROUP BY l_returnflag")
def op_quantile(spark, sf):
    return table(spark, sf, "lineitem").groupBy("l_returnflag").agg(F.round(F.percentile("l_extendedprice", F.lit(0.5)), 4).alias("median"), F.expr("percentile_disc(0.9) WITHIN GROUP (ORDER BY l_quantity)").alias("q90"))


@query()
def op_approx_distinct(spark, sf):
    return table(spark, sf, "lineitem").groupBy("l_returnflag").agg(F.approx_count_distinct("l_partkey", 0.02).alias("n"))


@query("SELECT strftime(time_bucket(INTERVAL 1 HOUR, ts), '%Y-%m-%d %H:%M:%S') AS start, count(*) AS n, round(sum(value), 4) AS v FROM events GROUP BY 1")
def op_tumbling(spark, sf):
    w = F.window("ts", "1 hour")
    return table(spark, sf, "events").groupBy(w.alias("w")).agg(F.count(F.lit(1)).alias("n"), F.round(F.sum("value"), 4).alias("v")).select(F.date_format("w.start", "yyyy-MM-dd HH:mm:ss").alias("start"), "n", "v")


@query("SELECT strftime(s, '%Y-%m-%d %H:%M:%S') AS start, count(*) AS n FROM (SELECT unnest([time_bucket(INTERVAL 30 MINUTE, ts), time_bucket(INTERVAL 30 MINUTE, ts) - INTERVAL 30 MINUTE]) AS s FROM events) GROUP BY 1")
def op_sliding(spark, sf):
    w = F.window("ts", "1 hour", "30 minutes")
    return table(spark, sf, "events").groupBy(w.alias("w")).agg(F.count(F.lit(1)).alias("n")).select(F.date_format("w.start", "yyyy-MM-dd HH:mm:ss").alias("start"), "n")


@query("""WITH g AS (SELECT *, CASE WHEN ts < lag(ts) OVER w + INTERVAL 12 HOUR THEN 0 ELSE 1 END AS new FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)),
s AS (SELECT *, sum(new) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS UNBOUNDED PRECEDING) AS s FROM g) SELECT user_id, strftime(min(ts), '%Y-%m-%d %H:%M:%S') AS start, count(*) AS n FROM s GROUP BY user_id, s""")
def op_session(spark, sf):
    w = F.session_window("ts", "12 hours")
    return table(spark, sf, "events").groupBy("user_id", w.alias("w")).agg(F.count(F.lit(1)).alias("n")).select("user_id", F.date_format("w.start", "yyyy-MM-dd HH:mm:ss").alias("start"), "n")


@query(f"WITH {PROBE} SELECT og.g, h.g IS NOT NULL AS hit FROM og LEFT JOIN (SELECT g FROM hits WHERE c = 3 AND rep = 3) h ON h.g = og.g")
def op_udf(spark, sf):
    """The containment kernel as a scalar function, against the relational plan of SQL."""
    from .functions.iso import contains
    from .model import Graph

    pattern = Graph.of(["5-LOW", "MEDIUM", "ASIA"], [0, 1], [1, 2], ["R", "O"])

    @F.pandas_udf(T.BooleanType())
    def inside(vl: pd.Series, eu: pd.Series, ew: pd.Series, el: pd.Series) -> pd.Series:
        return pd.Series([contains(Graph.of(*row), pattern) for row in zip(vl, eu, ew, el)])

    return _graphs(spark, sf).select(F.col("graph_id").alias("g"), inside("vl", "eu", "ew", "el").alias("hit"))


@query(f"WITH {PROBE} SELECT c AS cluster_id, round(11.0 / 3 / avg(gsize), 6) AS hcov FROM asg WHERE c > 0 GROUP BY c")
def op_udaf(spark, sf):
    """Approximate coverage as a grouped-aggregate function, over parts of a cluster: no worker holds a whole one."""

    @F.pandas_udf(T.ArrayType(T.DoubleType()))
    def summed(sizes: pd.Series) -> list:
        return [float(sizes.sum()), float(len(sizes))]

    from .operators import probe

    assigned = probe.assign(_graphs(spark, sf), probe.region_probes()).where("cluster_id > 0")
    parts = assigned.groupBy("cluster_id", F.pmod(F.xxhash64("graph_id"), F.lit(64)).alias("part")).agg(summed(F.col("gsize")).alias("s"))
    return parts.groupBy("cluster_id").agg(F.round(F.lit(11.0 / 3) / (F.sum(F.col("s")[0]) / F.sum(F.col("s")[1])), 6).alias("hcov"))


@query(f"WITH {ORDER} SELECT g, count(*) AS n_paths FROM (SELECT DISTINCT g, least(la, lb), le, greatest(la, lb) FROM ot) GROUP BY g")
def op_udtf(spark, sf):
    """Distinct length-1 paths of each graph as a table function."""

    @F.udtf(returnType="path string")
    class Paths:
        def eval(self, vl, eu, ew, el):
            for p in {(min(vl[u], vl[w]), x, max(vl[u], vl[w])) for u, w, x in zip(eu, ew, el)}:
                yield ("|".join(p),)

    spark.udtf.register("graph_paths", Paths)
    _graphs(spark, sf).createOrReplaceTempView("order_graphs")
    return spark.sql("SELECT graph_id AS g, count(*) AS n_paths FROM order_graphs, LATERAL graph_paths(vl, eu, ew, el) GROUP BY graph_id")



@query("SELECT l_orderkey, l_linenumber, bit_count(xor(l_partkey, l_suppkey))::BIGINT AS far, (l_partkey & 255)::BIGINT AS low, (l_partkey >> 4)::BIGINT AS high FROM lineitem")
def op_bits(spark, sf):
    pairs = table(spark, sf, "lineitem").select("l_orderkey", "l_linenumber", "l_partkey", "l_suppkey")
    far = F.bit_count(F.col("l_partkey").bitwiseXOR(F.col("l_suppkey"))).cast("bigint")
    return pairs.select("l_orderkey", "l_linenumber", far.alias("far"), F.col("l_partkey").bitwiseAND(F.lit(255)).alias("low"), F.shiftright("l_partkey", 4).alias("high"))


_drawn = "('0x' || substr(md5(o_orderkey || ':draw'), 1, 7))::BIGINT"


def _draw():
    return F.conv(F.substring(F.md5(F.concat(F.col("o_orderkey").cast("string"), F.lit(":draw"))), 1, 7), 16, 10).cast("bigint")


@query(f"SELECT o_orderkey, o_orderpriority FROM orders WHERE {_drawn} < 0.1 * 268435456")
def op_sample_bernoulli(spark, sf):
    """Each row by a draw of its own, the same wherever it is computed."""
    return table(spark, sf, "orders").where(_draw() < 0.1 * (1 << 28)).select("o_orderkey", "o_orderpriority")


@query(f"""WITH s AS (SELECT unnest(['1-URGENT', '2-HIGH', '3-MEDIUM', '4-NOT SPECIFIED', '5-LOW']) AS p, unnest([0.5, 0.2, 0.1, 0.1, 0.05]) AS share)
SELECT o_orderkey, o_orderpriority FROM orders JOIN s ON p = o_orderpriority WHERE {_drawn} < share * 268435456""")
def op_sample_stratified(spark, sf):
    """A share of its own for each priority."""
    share = F.create_map(*[F.lit(x) for pair in (("1-URGENT", 0.5), ("2-HIGH", 0.2), ("3-MEDIUM", 0.1), ("4-NOT SPECIFIED", 0.1), ("5-LOW", 0.05)) for x in pair])
    return table(spark, sf, "orders").where(_draw() < F.element_at(share, F.col("o_orderpriority")) * float(1 << 28)).select("o_orderkey", "o_orderpriority")


@query("""SELECT coalesce(c.n, s.n) AS nation, coalesce(c.k, 0) AS customers, coalesce(s.k, 0) AS suppliers
FROM (SELECT c_nationkey AS n, count(*) AS k FROM customer WHERE c_acctbal < 0 GROUP BY 1) c FULL JOIN (SELECT s_nationkey AS n, count(*) AS k FROM supplier GROUP BY 1) s ON c.n = s.n""")
def op_cogroup(spark, sf):
    """Two tables side by side for each key, counts before the exchange so that a group is a few rows."""
    import pyarrow as pa

    def counted(df, key):
        return df.groupBy(F.col(key).cast("bigint").alias("nation")).agg(F.count(F.lit(1)).alias("k"))

    def joined(left: pa.Table, right: pa.Table) -> pa.Table:
        total = lambda t: sum(t.column("k").to_pylist())
        key = (left if left.num_rows else right).column("nation")[0].as_py()
        return pa.table({"nation": pa.array([key], pa.int64()), "customers": pa.array([total(left)], pa.int64()), "suppliers": pa.array([total(right)], pa.int64())})

    c, s = counted(table(spark, sf, "customer").where("c_acctbal < 0"), "c_nationkey"), counted(table(spark, sf, "supplier"), "s_nationkey")
    return c.groupBy("nation").cogroup(s.groupBy("nation")).applyInArrow(joined, "nation bigint, customers bigint, suppliers bigint")
