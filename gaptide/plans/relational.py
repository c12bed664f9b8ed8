"""Registered queries of the relational operators around the methods: joins, aggregates, windows, sets, scalars, streams."""

from __future__ import annotations

from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ..common import table, unit_draw
from ..sources import features as X
from ..streaming import events as EV
from . import sqlparts as Q
from .gapqueries import c, r6

QUERIES, SQL = {}, {}


def query(sql=None, name=None):
    def put(f):
        QUERIES[name or f.__name__] = f
        if sql:
            SQL[name or f.__name__] = sql
        return f

    return put


@query("SELECT n_name, count(*) AS n, round(sum(l_extendedprice), 2) AS price FROM lineitem JOIN supplier ON l_suppkey = s_suppkey JOIN nation ON s_nationkey = n_nationkey GROUP BY 1")
def join_star(spark, sf_dir):
    line, s, n = table(spark, sf_dir, "lineitem", "l_suppkey", "l_extendedprice"), table(spark, sf_dir, "supplier", "s_suppkey", "s_nationkey"), table(spark, sf_dir, "nation", "n_nationkey", "n_name")
    return line.join(s, line.l_suppkey == s.s_suppkey).join(n, s.s_nationkey == n.n_nationkey).groupBy("n_name").agg(F.count(F.lit(1)).alias("n"), F.round(F.sum("l_extendedprice"), 2).alias("price"))


@query("SELECT o_orderkey FROM orders WHERE o_orderkey NOT IN (SELECT l_orderkey FROM lineitem)")
def join_anti(spark, sf_dir):
    return table(spark, sf_dir, "orders", "o_orderkey").join(table(spark, sf_dir, "lineitem", F.col("l_orderkey").alias("o_orderkey")), "o_orderkey", "left_anti")


@query("SELECT count(*) AS n FROM orders WHERE o_orderkey IN (SELECT l_orderkey FROM lineitem WHERE l_quantity > 45)")
def join_semi(spark, sf_dir):
    big = table(spark, sf_dir, "lineitem").where("l_quantity > 45").select(c("l_orderkey").alias("o_orderkey"))
    return table(spark, sf_dir, "orders", "o_orderkey").join(big, "o_orderkey", "left_semi").agg(F.count(F.lit(1)).alias("n"))


OLD_NEW = f"WITH o AS (SELECT vec_id FROM embeddings WHERE {Q.draw('o', 'vec_id')} < 0.4), n AS (SELECT vec_id FROM embeddings WHERE {Q.draw('n', 'vec_id')} < 0.4)"


def _blocks(spark, sf_dir):
    e = table(spark, sf_dir, "embeddings", "vec_id")
    return e.where(unit_draw("o", c("vec_id")) < 0.4), e.where(unit_draw("n", c("vec_id")) < 0.4)


@query(OLD_NEW + " SELECT coalesce(o.vec_id, n.vec_id) AS vec_id, CASE WHEN o.vec_id IS NULL THEN 'in' WHEN n.vec_id IS NULL THEN 'out' ELSE 'kept' END AS what FROM o FULL OUTER JOIN n ON o.vec_id = n.vec_id")
def join_full_outer(spark, sf_dir):
    old, new = _blocks(spark, sf_dir)
    both = old.withColumn("o", F.lit(1)).join(new.withColumn("n", F.lit(1)), "vec_id", "full_outer")
    return both.select("vec_id", F.when(c("o").isNull(), "in").when(c("n").isNull(), "out").otherwise("kept").alias("what"))


@query(OLD_NEW + " SELECT vec_id, 'kept' AS what FROM (SELECT * FROM o INTERSECT SELECT * FROM n) UNION ALL SELECT vec_id, 'swapped' FROM (SELECT * FROM n EXCEPT SELECT * FROM o)")
def setop_swaps(spark, sf_dir):
    old, new = _blocks(spark, sf_dir)
    return old.intersect(new).withColumn("what", F.lit("kept")).union(new.exceptAll(old).withColumn("what", F.lit("swapped")))


@query("WITH e AS (SELECT vec_id, unnest(generate_series(0, 63)) AS r, unnest(embedding)::DOUBLE AS x FROM embeddings WHERE vec_id < 12) SELECT a.vec_id AS i, b.vec_id AS j, round(sum(a.x * b.x), 6) + 0.0 AS x FROM e a JOIN e b USING (r) WHERE a.vec_id <= b.vec_id GROUP BY 1, 2")
def join_gram_block(spark, sf_dir):
    e = X.emb_cells(spark, sf_dir).where("row_id < 12")
    a, b = e.select(c("row_id").alias("i"), "coord_id", c("x").alias("xi")), e.select(c("row_id").alias("j"), "coord_id", c("x").alias("xj"))
    return a.join(b, "coord_id").where("i <= j").groupBy("i", "j").agg(r6(F.sum(c("xi") * c("xj"))).alias("x"))


@query("WITH e AS (SELECT vec_id, unnest(generate_series(0, 63)) AS c, unnest(embedding)::DOUBLE AS x FROM embeddings) SELECT a.c AS i, b.c AS j, round(sum(a.x * b.x), 6) + 0.0 AS x FROM e a JOIN e b USING (vec_id) WHERE a.c <= b.c GROUP BY 1, 2")
def join_gram_features(spark, sf_dir):
    """The Gram matrix of all features over all rows: pairs meet by row, and only sums of pairs leave a partition."""
    e = X.emb_cells(spark, sf_dir)
    a, b = e.select("row_id", c("coord_id").alias("i"), c("x").alias("xi")), e.select("row_id", c("coord_id").alias("j"), c("x").alias("xj"))
    return a.join(b, "row_id").where("i <= j").groupBy("i", "j").agg(r6(F.sum(c("xi") * c("xj"))).alias("x"))


@query("WITH e AS (SELECT event_id, user_id, ts, value FROM events), p AS (SELECT event_id, user_id, ts FROM events WHERE event_type = 'purchase') SELECT p.event_id, (SELECT arg_max(e.event_id, (e.ts, e.event_id)) FROM e WHERE e.user_id = p.user_id AND (e.ts < p.ts)) AS before_id FROM p")
def asof_last_event(spark, sf_dir):
    """The newest event of the user before each purchase: one sort by user and time, no range join."""
    e = table(spark, sf_dir, "events", "event_id", "user_id", "ts", "event_type")
    w = W.partitionBy("user_id").orderBy(c("ts").cast("timestamp").cast("long") * 1000000 + F.date_format("ts", "SSSSSS").cast("long")).rangeBetween(W.unboundedPreceding, -1)
    last = F.max(F.struct("ts", "event_id")).over(w)
    return e.withColumn("b", last["event_id"]).where("event_type = 'purchase'").select("event_id", c("b").alias("before_id"))


@query("WITH v AS (SELECT event_id, value FROM events), b AS (SELECT unnest(generate_series(0, (SELECT floor(max(value) / 10)::BIGINT FROM events))) AS k) SELECT k::INT AS bin, count(*) AS n, round(sum(value), 6) AS total FROM v JOIN b ON value >= k * 10 AND value < (k + 1) * 10 GROUP BY 1")
def range_join_bins(spark, sf_dir):
    """Values in intervals, as many as cover them all: an equi-join on the bin that they fall in, then the bounds as they are."""
    v = table(spark, sf_dir, "events", "value").withColumn("bin", F.floor(c("value") / 10).cast("int"))
    b = v.agg(F.max("bin").alias("last")).select(F.explode(F.sequence(F.lit(0), "last")).alias("bin"))
    return v.join(b, "bin").where((c("value") >= c("bin") * 10) & (c("value") < (c("bin") + 1) * 10)).groupBy("bin").agg(F.count(F.lit(1)).alias("n"), r6(F.sum("value")).alias("total"))


@query("SELECT coord_id, count(*) AS nnz FROM (SELECT vec_id AS coord_id, unnest(embedding) AS x FROM embeddings) WHERE x > 0 GROUP BY 1")
def lateral_explode(spark, sf_dir):
    table(spark, sf_dir, "embeddings").createOrReplaceTempView("emb_lateral")
    return spark.sql("SELECT vec_id AS coord_id, count(*) AS nnz FROM emb_lateral LATERAL VIEW posexplode(embedding) t AS p, x WHERE x > 0 GROUP BY vec_id")


@query("SELECT l_returnflag, l_linestatus, sum(l_quantity) AS qty, round(avg(l_discount), 6) AS discount, min(l_tax) AS tax_min, max(l_tax) AS tax_max, count(*) AS n, count(DISTINCT l_suppkey) AS suppliers, round(stddev_samp(l_quantity), 6) AS sd, round(corr(l_quantity, l_extendedprice), 6) AS r FROM lineitem GROUP BY 1, 2")
def agg_summary(spark, sf_dir):
    line = table(spark, sf_dir, "lineitem")
    return line.groupBy("l_returnflag", "l_linestatus").agg(F.sum("l_quantity").alias("qty"), r6(F.avg("l_discount")).alias("discount"), F.min("l_tax").alias("tax_min"), F.max("l_tax").alias("tax_max"), F.count(F.lit(1)).alias("n"), F.count_distinct("l_suppkey").alias("suppliers"), r6(F.stddev("l_quantity")).alias("sd"), r6(F.corr("l_quantity", "l_extendedprice")).alias("r"))


@query("SELECT user_id, max_by(event_id, (value, event_id)) AS best, min_by(event_id, (value, event_id)) AS least FROM events GROUP BY 1")
def agg_argmax(spark, sf_dir):
    return table(spark, sf_dir, "events").groupBy("user_id").agg(F.max_by("event_id", F.struct("value", "event_id")).alias("best"), F.min_by("event_id", F.struct("value", "event_id")).alias("least"))


@query("SELECT event_type, round(quantile_cont(value, 0.5), 6) AS median, round(quantile_cont(value, 0.9), 6) AS p90 FROM events GROUP BY 1")
def agg_quantiles(spark, sf_dir):
    return table(spark, sf_dir, "events").groupBy("event_type").agg(r6(F.percentile("value", F.lit(0.5))).alias("median"), r6(F.percentile("value", F.lit(0.9))).alias("p90"))


@query("SELECT floor(log2(value))::INT AS bin, count(*) AS n FROM events WHERE value > 0 GROUP BY 1")
def agg_histogram(spark, sf_dir):
    return table(spark, sf_dir, "events").where("value > 0").groupBy(F.floor(F.log2("value")).cast("int").alias("bin")).agg(F.count(F.lit(1)).alias("n"))


@query("SELECT p, round(sum(x), 6) + 0.0 AS x FROM (SELECT unnest(generate_series(0, 63))::INT AS p, unnest(embedding)::DOUBLE * " + Q.draw("a", "vec_id") + " AS x FROM embeddings) GROUP BY 1")
def agg_vector_sum(spark, sf_dir):
    return table(spark, sf_dir, "embeddings").select(unit_draw("a", c("vec_id")).alias("a"), F.posexplode("embedding").alias("p", "x")).groupBy("p").agg(r6(F.sum(c("x").cast("double") * c("a"))).alias("x"))


@query("SELECT o_orderstatus, o_orderpriority, count(*) AS n, grouping_id(o_orderstatus, o_orderpriority)::BIGINT AS level FROM orders GROUP BY CUBE (o_orderstatus, o_orderpriority)")
def cube_orders(spark, sf_dir):
    return table(spark, sf_dir, "orders").cube("o_orderstatus", "o_orderpriority").agg(F.count(F.lit(1)).alias("n"), F.grouping_id().alias("level"))


@query("SELECT p_brand, p_type, count(*) AS n FROM part GROUP BY ROLLUP (p_brand, p_type)")
def rollup_parts(spark, sf_dir):
    return table(spark, sf_dir, "part").rollup("p_brand", "p_type").agg(F.count(F.lit(1)).alias("n"))


@query("SELECT user_id, count(*) FILTER (event_type = 'view') AS view, count(*) FILTER (event_type = 'click') AS click, count(*) FILTER (event_type = 'purchase') AS purchase FROM events GROUP BY 1")
def pivot_events(spark, sf_dir):
    return table(spark, sf_dir, "events").groupBy("user_id").pivot("event_type", ["view", "click", "purchase"]).agg(F.count(F.lit(1))).na.fill(0)


@query("SELECT l_orderkey, name, round(sum(x), 6) AS x FROM (UNPIVOT (SELECT l_orderkey, l_linenumber, l_quantity, l_discount, l_tax FROM lineitem WHERE l_orderkey < 50) ON l_quantity, l_discount, l_tax INTO NAME name VALUE x) GROUP BY 1, 2")
def unpivot_lineitem(spark, sf_dir):
    line = table(spark, sf_dir, "lineitem", "l_orderkey", "l_linenumber", "l_quantity", "l_discount", "l_tax").where("l_orderkey < 50")
    return line.unpivot(["l_orderkey", "l_linenumber"], ["l_quantity", "l_discount", "l_tax"], "name", "x").groupBy("l_orderkey", "name").agg(r6(F.sum("x")).alias("x"))


@query("SELECT l_orderkey, name, round(sum(x), 6) AS x FROM (UNPIVOT (SELECT l_orderkey, l_linenumber, l_quantity, l_discount, l_tax FROM lineitem) ON l_quantity, l_discount, l_tax INTO NAME name VALUE x) GROUP BY 1, 2")
def unpivot_lineitem_whole(spark, sf_dir):
    line = table(spark, sf_dir, "lineitem", "l_orderkey", "l_linenumber", "l_quantity", "l_discount", "l_tax")
    return line.unpivot(["l_orderkey", "l_linenumber"], ["l_quantity", "l_discount", "l_tax"], "name", "x").groupBy("l_orderkey", "name").agg(r6(F.sum("x")).alias("x"))


@query("SELECT event_id, row_number() OVER w AS rn, rank() OVER (PARTITION BY user_id ORDER BY event_type) AS rk, dense_rank() OVER (PARTITION BY user_id ORDER BY event_type) AS dr, ntile(4) OVER w AS quarter, round(cume_dist() OVER w, 6) AS cd FROM events WINDOW w AS (PARTITION BY user_id ORDER BY event_id)")
def window_ranks(spark, sf_dir):
    w, t = W.partitionBy("user_id").orderBy("event_id"), W.partitionBy("user_id").orderBy("event_type")
    return table(spark, sf_dir, "events").select("event_id", F.row_number().over(w).alias("rn"), F.rank().over(t).alias("rk"), F.dense_rank().over(t).alias("dr"), F.ntile(4).over(w).alias("quarter"), r6(F.cume_dist().over(w)).alias("cd"))


@query("SELECT event_id, round(value - lag(value) OVER w, 6) + 0.0 AS change, round(sum(value) OVER (w ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW), 6) AS running, round(avg(value) OVER (w ROWS BETWEEN 2 PRECEDING AND CURRENT ROW), 6) AS moving, min(value) OVER (w ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW) AS best FROM events WINDOW w AS (PARTITION BY user_id ORDER BY event_id)")
def window_running(spark, sf_dir):
    w = W.partitionBy("user_id").orderBy("event_id")
    so_far = w.rowsBetween(W.unboundedPreceding, 0)
    return table(spark, sf_dir, "events").select("event_id", r6(c("value") - F.lag("value").over(w)).alias("change"), r6(F.sum("value").over(so_far)).alias("running"), r6(F.avg("value").over(w.rowsBetween(-2, 0))).alias("moving"), F.min("value").over(so_far).alias("best"))


@query("SELECT event_id, last_value(CASE WHEN event_type = 'purchase' THEN value END IGNORE NULLS) OVER (PARTITION BY user_id ORDER BY event_id ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW) AS last_purchase FROM events")
def window_last_known(spark, sf_dir):
    w = W.partitionBy("user_id").orderBy("event_id").rowsBetween(W.unboundedPreceding, 0)
    return table(spark, sf_dir, "events").select("event_id", F.last(F.when(c("event_type") == "purchase", c("value")), ignorenulls=True).over(w).alias("last_purchase"))


@query("SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY floor(value) RANGE BETWEEN 5 PRECEDING AND 5 FOLLOWING) AS near FROM events")
def window_value_range(spark, sf_dir):
    w = W.partitionBy("user_id").orderBy(F.floor("value")).rangeBetween(-5, 5)
    return table(spark, sf_dir, "events").select("event_id", F.count(F.lit(1)).over(w).alias("near"))


@query("SELECT o_custkey, o_orderkey FROM (SELECT o_custkey, o_orderkey, row_number() OVER (PARTITION BY o_custkey ORDER BY o_totalprice DESC, o_orderkey) AS r FROM orders) WHERE r <= 3")
def topk_per_key(spark, sf_dir):
    w = W.partitionBy("o_custkey").orderBy(F.desc("o_totalprice"), "o_orderkey")
    return table(spark, sf_dir, "orders").withColumn("r", F.row_number().over(w)).where("r <= 3").select("o_custkey", "o_orderkey")


@query("SELECT DISTINCT l_orderkey, l_partkey FROM lineitem")
def dedup_lineitem(spark, sf_dir):
    return table(spark, sf_dir, "lineitem").dropDuplicates(["l_orderkey", "l_partkey"]).select("l_orderkey", "l_partkey")


@query("SELECT event_id, round(sqrt(value), 6) AS root, round(ln(1 + value), 6) AS l, round(pow(value, 0.3), 6) AS p, sign(value - 50)::DOUBLE AS s, greatest(value, 50.0) AS g, least(value, 50.0) AS m, (event_id * 7) % 5 AS pm FROM events")
def scalar_math(spark, sf_dir):
    v = c("value")
    return table(spark, sf_dir, "events").select("event_id", r6(F.sqrt(v)).alias("root"), r6(F.log1p(v)).alias("l"), r6(F.pow(v, F.lit(0.3))).alias("p"), F.signum(v - 50).alias("s"), F.greatest(v, F.lit(50.0)).alias("g"), F.least(v, F.lit(50.0)).alias("m"), F.pmod(c("event_id") * 7, F.lit(5)).alias("pm"))


@query("SELECT doc_id, upper(substr(source, 1, 3)) AS head, length(source) AS n, md5(text) AS h, lower(lang) || '-' || source AS joined FROM documents")
def scalar_strings(spark, sf_dir):
    return table(spark, sf_dir, "documents").select("doc_id", F.upper(F.substring("source", 1, 3)).alias("head"), F.length("source").cast("long").alias("n"), F.md5("text").alias("h"), F.concat_ws("-", F.lower("lang"), "source").alias("joined"))


@query("SELECT strftime(date_trunc('month', ts), '%Y-%m-%d') AS month, extract(hour FROM ts)::INT AS hour, count(*) AS n FROM events GROUP BY 1, 2")
def scalar_dates(spark, sf_dir):
    return table(spark, sf_dir, "events").groupBy(F.date_format(F.date_trunc("month", "ts"), "yyyy-MM-dd").alias("month"), F.hour("ts").alias("hour")).agg(F.count(F.lit(1)).alias("n"))


@query("SELECT (props->>'$.k')::INT AS k, count(*) AS n, round(sum(value), 6) AS total FROM events GROUP BY 1")
def json_props(spark, sf_dir):
    e = table(spark, sf_dir, "events").select(F.from_json("props", "k int").alias("p"), "value")
    return e.groupBy(c("p.k").alias("k")).agg(F.count(F.lit(1)).alias("n"), r6(F.sum("value")).alias("total"))


@query("SELECT vec_id, round(list_sum(list_transform(embedding, lambda x: abs(x::DOUBLE))), 6) AS l1, len(list_filter(embedding, lambda x: x > 0.1))::INT AS big, round(list_max(embedding)::DOUBLE, 6) AS top FROM embeddings")
def scalar_arrays(spark, sf_dir):
    e = c("embedding").cast("array<double>")
    return table(spark, sf_dir, "embeddings").select("vec_id", r6(F.aggregate(e, F.lit(0.0), lambda s, x: s + F.abs(x))).alias("l1"), F.size(F.filter("embedding", lambda x: x > F.lit(0.1))).alias("big"), r6(F.array_max(e)).alias("top"))


@query("SELECT page_id, length(coalesce(html, '')) AS chars, len(regexp_extract_all(coalesce(html, ''), '<a ')) AS links, len(regexp_extract_all(coalesce(html, ''), '<p>')) AS paragraphs, regexp_extract(url, '^https?://([^/?#]+)', 1) AS host FROM pages")
def page_stats(spark, sf_dir):
    return X.page_stats(spark, sf_dir).withColumn("chars", c("chars").cast("long"))


@query("SELECT conv_id, count(*) AS turns, sum(length(text))::BIGINT AS chars, count(*) FILTER (role = 'user') AS user_turns FROM conversations GROUP BY 1")
def conv_stats(spark, sf_dir):
    return X.conv_stats(spark, sf_dir)


@query(r"SELECT doc_id, length(t) AS chars, len(regexp_extract_all(t, '[^\x20\x09-\x0D]+')) AS words, len(regexp_extract_all(t, chr(10))) + 1 AS lines, len(regexp_extract_all(t, '[0-9]')) AS digits, len(regexp_extract_all(t, '[A-Z]')) AS capitals FROM (SELECT doc_id, coalesce(text, '') AS t FROM documents)")
def doc_stats(spark, sf_dir):
    return X.doc_stats(spark, sf_dir).withColumn("chars", c("chars").cast("long"))


@query(r"""WITH i AS (SELECT list_filter(regexp_split_to_array(lower(text), '[\x20\x09-\x0D]+'), lambda x: x <> '') AS w FROM benchmark), d AS (SELECT doc_id, list_filter(regexp_split_to_array(lower(text), '[\x20\x09-\x0D]+'), lambda x: x <> '') AS w FROM documents),
gi AS (SELECT DISTINCT unnest(list_transform(range(1, len(w) - 6), lambda k: array_to_string(w[k:k + 7], ' '))) AS g FROM i WHERE len(w) >= 8), gd AS (SELECT DISTINCT doc_id, unnest(list_transform(range(1, len(w) - 6), lambda k: array_to_string(w[k:k + 7], ' '))) AS g FROM d WHERE len(w) >= 8)
SELECT doc_id, count(*) AS shared FROM gd WHERE g IN (SELECT g FROM gi) GROUP BY 1""")
def benchmark_overlap(spark, sf_dir):
    return X.benchmark_overlap(spark, sf_dir)


@query("SELECT user_id, count(*) AS events, round(sum(value), 6) AS value, round(avg(extract(hour FROM ts)), 6) AS mean_hour, round(avg((props->>'$.k')::DOUBLE), 6) AS mean_k, count(*) FILTER (event_type = 'view') AS n_view, count(*) FILTER (event_type = 'click') AS n_click, count(*) FILTER (event_type = 'purchase') AS n_purchase FROM events GROUP BY 1")
def event_user_features(spark, sf_dir):
    return X.event_user_features(spark, sf_dir)


@query("SELECT row_number() OVER (ORDER BY l_orderkey, l_partkey, l_suppkey, l_linenumber, l_quantity, l_extendedprice, l_discount, l_tax, l_returnflag, l_linestatus, l_shipdate) - 1 AS coord_id, round(l_extendedprice, 2) AS price, round(l_quantity / 50.0, 6) AS q FROM lineitem")
def coo_star(spark, sf_dir):
    return X.star_samples(spark, sf_dir).select("coord_id", F.round(c("y") * 100000, 2).alias("price"), r6(F.get("vals", 0)).alias("q"))


@query("SELECT o_orderstatus, o_orderpriority, count(*) AS n, grouping_id(o_orderstatus, o_orderpriority)::BIGINT AS level FROM orders GROUP BY GROUPING SETS ((o_orderstatus, o_orderpriority), (o_orderpriority), ())")
def grouping_sets_orders(spark, sf_dir):
    o = table(spark, sf_dir, "orders")
    return o.groupingSets([["o_orderstatus", "o_orderpriority"], ["o_orderpriority"], []], "o_orderstatus", "o_orderpriority").agg(F.count(F.lit(1)).alias("n"), F.grouping_id().alias("level"))


@query("SELECT a.s_suppkey, count(*) AS richer FROM supplier a JOIN supplier b ON b.s_acctbal > a.s_acctbal GROUP BY 1")
def join_theta(spark, sf_dir):
    """How many are greater, without comparing pairs: rows of a value share its rank, ranks within ranges are offset by the counts of the ranges above."""
    s = table(spark, sf_dir, "supplier", "s_suppkey", "s_acctbal")
    ranged = s.groupBy("s_acctbal").agg(F.count(F.lit(1)).alias("n"))
    span = F.floor(c("s_acctbal") / 256)
    inside = F.coalesce(F.sum("n").over(W.partitionBy("g").orderBy(F.desc("s_acctbal")).rowsBetween(W.unboundedPreceding, -1)), F.lit(0))
    values = ranged.withColumn("g", span).withColumn("inside", inside)
    above = values.groupBy("g").agg(F.sum("n").alias("m")).withColumn("above", F.coalesce(F.sum("m").over(W.orderBy(F.desc("g")).rowsBetween(W.unboundedPreceding, -1)), F.lit(0)))  # a row for each range of values
    return s.join(values.join(above, "g"), "s_acctbal").select("s_suppkey", (c("inside") + c("above")).alias("richer")).where("richer > 0")


@query("SELECT event_type, true AS near FROM events GROUP BY 1")
def agg_approx_distinct(spark, sf_dir):
    """Approximate numbers of different users and values are within a tenth of the exact ones."""
    near = lambda x: F.abs(F.approx_count_distinct(x, 0.02) - F.count_distinct(x)) <= 0.1 * F.count_distinct(x)
    return table(spark, sf_dir, "events").groupBy("event_type").agg((near("user_id") & near("value")).alias("near"))


@query("SELECT event_type, true AS near FROM events GROUP BY 1")
def agg_kll_quantile(spark, sf_dir):
    """The median by a mergeable sketch has between 45% and 55% of the values up to it."""
    e = table(spark, sf_dir, "events", "event_type", "value")
    at = e.groupBy("event_type").agg(F.expr("kll_sketch_get_quantile_double(kll_sketch_agg_double(value), 0.5D)").alias("at"))
    return e.join(F.broadcast(at), "event_type").groupBy("event_type").agg(F.avg(F.when(c("value") <= c("at"), 1.0).otherwise(0.0)).between(0.45, 0.55).alias("near"))  # a row for each of few types


@query("SELECT user_id, event_type AS kind, count(*) AS n, round(count(*) * 1.0 / sum(count(*)) OVER (PARTITION BY user_id), 6) AS share FROM events GROUP BY 1, 2")
def scalar_maps(spark, sf_dir):
    """A map of counts for each user, its values turned into shares, exploded again."""
    m = table(spark, sf_dir, "events", "user_id", "event_type").groupBy("user_id", "event_type").agg(F.count(F.lit(1)).alias("n")).groupBy("user_id").agg(F.map_from_entries(F.collect_list(F.struct("event_type", "n"))).alias("m"))
    total = F.aggregate(F.map_values("m"), F.lit(0).cast("long"), lambda s, x: s + x)
    part = m.select("user_id", "m", F.transform_values("m", lambda k, v: r6(v / total)).alias("p"))
    return part.select("user_id", F.explode("m").alias("kind", "n"), "p").select("user_id", "kind", "n", F.element_at("p", c("kind")).alias("share"))


@query("SELECT event_id, strftime(ts + INTERVAL 36 HOUR, '%Y-%m-%d') AS later, date_diff('day', TIMESTAMP '2024-01-01', ts)::INT AS days, (event_type LIKE 'p%') AS p, (event_type IS NOT DISTINCT FROM 'view') AS v FROM events")
def scalar_intervals(spark, sf_dir):
    e = table(spark, sf_dir, "events")
    return e.select("event_id", F.date_format(c("ts") + F.expr("INTERVAL 36 HOURS"), "yyyy-MM-dd").alias("later"), F.datediff("ts", F.lit("2024-01-01").cast("date")).alias("days"), c("event_type").like("p%").alias("p"), c("event_type").eqNullSafe("view").alias("v"))


@query("SELECT page_id, regexp_extract(url, '^https?://([^/?#]+)', 1) AS host FROM pages")
def scalar_urls(spark, sf_dir):
    return table(spark, sf_dir, "pages").select("page_id", F.coalesce(F.expr("try_parse_url(url, 'HOST')"), F.lit("")).alias("host"))


@query("SELECT event_id, nth_value(event_id, 2) OVER (PARTITION BY user_id ORDER BY event_id ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING) AS second FROM events")
def window_nth(spark, sf_dir):
    w = W.partitionBy("user_id").orderBy("event_id").rowsBetween(W.unboundedPreceding, W.unboundedFollowing)
    return table(spark, sf_dir, "events").select("event_id", F.nth_value("event_id", 2).over(w).alias("second"))


@query("SELECT o_orderpriority, count(*) AS n FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY 1")
def join_hints(spark, sf_dir):
    """The same join by sort and merge, by shuffled hash and, where the planner finds it small enough, as it likes: equal results."""
    line, orders = table(spark, sf_dir, "lineitem", "l_orderkey"), table(spark, sf_dir, "orders", "o_orderkey", "o_orderpriority")
    ways = [line.join(orders.hint(h) if h else orders, line.l_orderkey == orders.o_orderkey).groupBy("o_orderpriority").agg(F.count(F.lit(1)).alias("n")) for h in ("merge", "shuffle_hash", None)]
    return ways[0].intersect(ways[1]).intersect(ways[2])


@query("SELECT event_id AS coord_id, true AS ok FROM events WHERE event_type = 'purchase'")
def event_samples_checked(spark, sf_dir):
    """Purchases as samples: eight finite cells, an intercept, and target 1."""
    s = X.event_samples(spark, sf_dir).where("y = 1")
    vals = X.add_intercept(F.slice("vals", 1, 7))
    return s.select("coord_id", ((F.size("vals") == 8) & F.forall("vals", lambda x: x.isNotNull() & ~F.isnan(x)) & (vals == c("vals"))).alias("ok"))


@query("SELECT (('0x' || substr(md5('split0:' || event_id), 1, 8))::BIGINT + 0.5) / 4294967296.0 < 0.8 AS training, count(*) AS n FROM events GROUP BY 1")
def split_by_hash(spark, sf_dir):
    return table(spark, sf_dir, "events").groupBy(X.train_test_split(c("event_id")).alias("training")).agg(F.count(F.lit(1)).alias("n"))


# --- streams against their batch forms


@query("SELECT strftime(date_trunc('hour', ts), '%Y-%m-%d %H:%M:%S') AS start, event_type, count(*) AS n, round(sum(value), 6) AS v FROM events GROUP BY 1, 2")
def stream_tumbling(spark, sf_dir):
    return EV.drain(EV.tumbling(EV.source(spark, sf_dir)), "complete", "tumbling")


@query("SELECT strftime(s, '%Y-%m-%d %H:%M:%S') AS start, count(*) AS n FROM (SELECT unnest([time_bucket(INTERVAL 2 HOUR, ts) - INTERVAL 4 HOUR, time_bucket(INTERVAL 2 HOUR, ts) - INTERVAL 2 HOUR, time_bucket(INTERVAL 2 HOUR, ts)]) AS s FROM events) GROUP BY 1")
def stream_sliding(spark, sf_dir):
    return EV.drain(EV.sliding(EV.source(spark, sf_dir)), "complete", "sliding")


@query("WITH g AS (SELECT user_id, ts, CASE WHEN ts <= lag(ts) OVER (PARTITION BY user_id ORDER BY ts) + INTERVAL 12 HOUR THEN 0 ELSE 1 END AS new FROM events), s AS (SELECT user_id, ts, sum(new) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS k FROM g) SELECT user_id, strftime(min(ts), '%Y-%m-%d %H:%M:%S') AS start, count(*) AS n FROM s GROUP BY user_id, k")
def stream_session(spark, sf_dir):
    return EV.drain(EV.sessions(EV.source(spark, sf_dir)), "complete", "session")


@query("SELECT DISTINCT event_id, user_id, event_type FROM events")
def stream_dedup(spark, sf_dir):
    return EV.drain(EV.dedup(EV.source(spark, sf_dir)), "append", "dedup")


@query("SELECT a.user_id, a.event_id AS first_id, b.event_id AS then_id FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts >= a.ts AND b.ts <= a.ts + INTERVAL 30 MINUTE WHERE a.event_type = 'view' AND b.event_type = 'purchase'")
def stream_interval_join(spark, sf_dir):
    return EV.drain(EV.followed(EV.source(spark, sf_dir), EV.source(spark, sf_dir)), "append", "followed")


@query("SELECT greatest(0, sum(greatest(0, 1 - (0.5 * (props->>'$.k')::DOUBLE / 100 + 0.25)))) > 0.1 * 1000 AS retrain FROM events")
def stream_retrain(spark, sf_dir):
    """Whether arrivals bring enough gap beside a certificate of 1,000 to train again."""
    import numpy as np

    from ..functions.objectives import HingeSvmDual

    stream = EV.source(spark, sf_dir).select(c("event_id").alias("coord_id"), F.array(F.get_json_object("props", "$.k").cast("double") / 100, F.lit(1.0)).alias("vals"))
    arrived = EV.drain(stream, "append", "retrain", lambda batch: EV.new_coordinates(batch, HingeSvmDual(1.0), np.array([0.5, 0.25])))
    return spark.createDataFrame([(bool(EV.should_retrain(arrived, 1000.0)),)], "retrain boolean")


@query("SELECT event_id, c_mktsegment FROM events LEFT JOIN customer ON user_id = c_custkey")
def stream_static_join(spark, sf_dir):
    return EV.drain(EV.with_customers(EV.source(spark, sf_dir), table(spark, sf_dir, "customer")), "append", "static")


@query("SELECT event_id AS coord_id, 0.0::DOUBLE AS alpha, round(greatest(0, 1 - (0.5 * (props->>'$.k')::DOUBLE / 100 + 0.25)), 6) AS z FROM events")
def stream_new_coords(spark, sf_dir):
    """Arrivals as samples of a support vector machine, with the gap at a fixed dual point."""
    import numpy as np

    from ..functions.objectives import HingeSvmDual

    stream = EV.source(spark, sf_dir).select(c("event_id").alias("coord_id"), F.array(F.get_json_object("props", "$.k").cast("double") / 100, F.lit(1.0)).alias("vals"))
    each = lambda batch: EV.new_coordinates(batch, HingeSvmDual(1.0), np.array([0.5, 0.25]))
    return EV.drain(stream, "append", "coords", each).select("coord_id", "alpha", r6("z").alias("z"))


@query("SELECT user_id, count(*) AS n, round(sum(value), 6) AS z FROM events GROUP BY 1")
def stream_user_memory(spark, sf_dir):
    return EV.drain(EV.user_memory(EV.source(spark, sf_dir)), "update", "memory").groupBy("user_id").agg(F.max("n").alias("n"), F.round(F.max("z"), 6).alias("z"))
