"""The operators around paths: what is done with hits and with the tables they come from."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from treeloom.operators.ranges import as_of, broadcast_if_small, point_in_interval, salted_join
from treeloom.sources.trees import open_tree, table
from treeloom.workloads.registry import register

# --- projection, filters, expressions ---------------------------------------------------------------------------------


@register("op_projection", "SELECT p_partkey AS key, upper(p_brand) AS brand, p_size * 2 + 1 AS size2 FROM part")
def projection(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "part").select(F.col("p_partkey").alias("key"), F.upper("p_brand").alias("brand"), (F.col("p_size") * 2 + 1).alias("size2"))


@register("op_filters", "SELECT p_partkey FROM part WHERE (p_size BETWEEN 5 AND 20 OR p_brand IN ('Brand#1', 'Brand#2')) AND p_name LIKE '%a%' AND NOT p_type ILIKE '%tin' AND p_retailprice IS NOT NULL")
def filters(spark: SparkSession, sf_dir: str) -> DataFrame:
    c = F.col
    return table(spark, sf_dir, "part").filter((c("p_size").between(5, 20) | c("p_brand").isin("Brand#1", "Brand#2")) & c("p_name").like("%a%") & ~c("p_type").ilike("%tin") & c("p_retailprice").isNotNull()).select("p_partkey")


@register(
    "op_strings",
    "SELECT p_partkey, length(p_name) AS n, substr(p_name, 2, 4) AS sub, replace(p_name, ' ', '_') AS rep, reverse(p_name) AS rev, lpad(p_brand, 12, '*') AS pad, strpos(p_name, 'a')::INTEGER AS at, md5(p_name) AS digest, trim(p_type) AS trimmed, translate(p_name, 'ae', 'AE') AS tr, regexp_extract(p_brand, '([0-9]+)', 1) AS num FROM part",
)
def strings(spark: SparkSession, sf_dir: str) -> DataFrame:
    n = F.col("p_name")
    return table(spark, sf_dir, "part").select(
        "p_partkey", F.length(n).cast("long").alias("n"), F.substring(n, 2, 4).alias("sub"), F.replace(n, F.lit(" "), F.lit("_")).alias("rep"), F.reverse(n).alias("rev"), F.lpad("p_brand", 12, "*").alias("pad"),
        F.instr(n, "a").alias("at"), F.md5(n).alias("digest"), F.trim("p_type").alias("trimmed"), F.translate(n, "ae", "AE").alias("tr"), F.regexp_extract("p_brand", "([0-9]+)", 1).alias("num"),
    )


@register(
    "op_dates",
    "SELECT o_orderkey, year(o_orderdate)::INTEGER AS y, month(o_orderdate)::INTEGER AS m, day(o_orderdate)::INTEGER AS d, date_diff('day', DATE '1992-01-01', o_orderdate::DATE)::INTEGER AS days, strftime(date_trunc('month', o_orderdate), '%Y-%m-%d') AS month_start, strftime(o_orderdate + INTERVAL 3 MONTH, '%Y-%m-%d') AS later, epoch(o_orderdate)::BIGINT AS seconds FROM orders",
)
def dates(spark: SparkSession, sf_dir: str) -> DataFrame:
    d = F.col("o_orderdate")
    return table(spark, sf_dir, "orders").select(
        "o_orderkey", F.year(d).alias("y"), F.month(d).alias("m"), F.dayofmonth(d).alias("d"), F.datediff(d, F.lit("1992-01-01").cast("date")).alias("days"),
        F.date_format(F.date_trunc("month", d), "yyyy-MM-dd").alias("month_start"), F.date_format(F.add_months(d, 3), "yyyy-MM-dd").alias("later"), F.unix_timestamp(d).alias("seconds"),
    )


@register(
    "op_math",
    "SELECT l_orderkey, l_linenumber, round(l_extendedprice * (1 - l_discount), 4) AS net, floor(l_quantity / 7)::BIGINT AS q, (l_orderkey % 13)::BIGINT AS r, round(sqrt(l_quantity), 6) AS root, round(ln(l_extendedprice), 6) AS lg, greatest(l_tax, l_discount) AS hi, least(l_tax, l_discount) AS lo, bit_count(l_orderkey)::INTEGER AS bits, (l_linenumber << 3)::BIGINT AS shifted FROM lineitem",
)
def math_functions(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "lineitem").select(
        "l_orderkey", "l_linenumber", F.round(F.col("l_extendedprice") * (1 - F.col("l_discount")), 4).alias("net"), F.floor(F.col("l_quantity") / 7).alias("q"), (F.col("l_orderkey") % 13).alias("r"),
        F.round(F.sqrt("l_quantity"), 6).alias("root"), F.round(F.log("l_extendedprice"), 6).alias("lg"), F.greatest("l_tax", "l_discount").alias("hi"), F.least("l_tax", "l_discount").alias("lo"),
        F.bit_count("l_orderkey").alias("bits"), F.shiftleft(F.col("l_linenumber").cast("long"), 3).alias("shifted"),
    )


@register(
    "op_arrays",
    "SELECT vec_id, len(embedding)::INTEGER AS n, floor(list_dot_product(list_transform(embedding, lambda x: floor(1024 * x::DOUBLE)), list_transform(embedding, lambda x: floor(1024 * x::DOUBLE))))::BIGINT AS norm2, len(list_filter(embedding, lambda x: x > 0))::INTEGER AS positive, list_position(list_transform(embedding, lambda x: x > 0), true)::BIGINT AS first_positive FROM embeddings",
)
def arrays(spark: SparkSession, sf_dir: str) -> DataFrame:
    whole = F.transform("embedding", lambda x: F.floor(x.cast("double") * 1024))
    return table(spark, sf_dir, "embeddings").select(
        "vec_id", F.size("embedding").alias("n"), F.aggregate(F.zip_with(whole, whole, lambda a, b: a * b), F.lit(0).cast("long"), lambda s, x: s + x).alias("norm2"),
        F.size(F.filter("embedding", lambda x: x > 0)).alias("positive"), F.array_position(F.transform("embedding", lambda x: x > 0), True).alias("first_positive"),
    )


@register("op_json", "SELECT event_id, (props->>'$.k')::BIGINT AS k, event_type || ':' || (props->>'$.k') AS tag FROM events")
def json_functions(spark: SparkSession, sf_dir: str) -> DataFrame:
    k = F.from_json("props", "k long")["k"]
    return table(spark, sf_dir, "events").select("event_id", k.alias("k"), F.concat_ws(":", "event_type", F.get_json_object("props", "$.k")).alias("tag"))


@register("op_variant", "SELECT event_id, (props->>'$.k')::BIGINT AS k FROM events WHERE (props->>'$.k')::BIGINT % 2 = 0")
def variant(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "events").select("event_id", F.expr("variant_get(parse_json(props), '$.k', 'bigint')").alias("k")).filter("k % 2 = 0")


@register("op_conditional", "SELECT o_orderkey, CASE WHEN o_totalprice > 200000 THEN 'high' WHEN o_totalprice > 100000 THEN 'mid' ELSE 'low' END AS band, coalesce(nullif(o_orderstatus, 'P'), 'pending') AS state, try_cast(o_orderpriority AS INTEGER) IS NULL AS not_number FROM orders")
def conditional(spark: SparkSession, sf_dir: str) -> DataFrame:
    band = F.when(F.col("o_totalprice") > 200000, "high").when(F.col("o_totalprice") > 100000, "mid").otherwise("low")
    return table(spark, sf_dir, "orders").select("o_orderkey", band.alias("band"), F.coalesce(F.nullif("o_orderstatus", F.lit("P")), F.lit("pending")).alias("state"), F.expr("try_cast(o_orderpriority as int) is null").alias("not_number"))


# --- joins --------------------------------------------------------------------------------------------------------------


@register("op_join_broadcast", "SELECT c_custkey, n_name, r_name FROM customer JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey")
def join_broadcast(spark: SparkSession, sf_dir: str) -> DataFrame:
    nation, region = table(spark, sf_dir, "nation"), table(spark, sf_dir, "region")
    small = broadcast_if_small(nation.join(region, nation["n_regionkey"] == region["r_regionkey"]).select("n_nationkey", "n_name", "r_name"), 10_000)
    c = table(spark, sf_dir, "customer")
    return c.join(small, c["c_nationkey"] == small["n_nationkey"]).select("c_custkey", "n_name", "r_name")


@register("op_join_sort_merge", "SELECT o_orderkey, l_linenumber, c_custkey FROM orders JOIN lineitem ON o_orderkey = l_orderkey JOIN customer ON o_custkey = c_custkey")
def join_sort_merge(spark: SparkSession, sf_dir: str) -> DataFrame:
    o, l, c = (table(spark, sf_dir, t) for t in ("orders", "lineitem", "customer"))
    return o.join(l.hint("merge"), o["o_orderkey"] == l["l_orderkey"]).join(c.hint("merge"), o["o_custkey"] == c["c_custkey"]).select("o_orderkey", "l_linenumber", "c_custkey")


@register("op_join_semi_anti", "SELECT c_custkey, EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey) AS orders FROM customer")
def join_semi_anti(spark: SparkSession, sf_dir: str) -> DataFrame:
    c, o = table(spark, sf_dir, "customer"), table(spark, sf_dir, "orders")
    hit = c["c_custkey"] == o["o_custkey"]
    with_, without = c.join(o, hit, "left_semi"), c.join(o, hit, "left_anti")
    return with_.select("c_custkey", F.lit(True).alias("orders")).unionAll(without.select("c_custkey", F.lit(False).alias("orders")))


@register("op_join_outer", "SELECT coalesce(d.doc_id, l.doc_id) AS doc_id, coalesce(quality, -1) AS quality, lang FROM documents d FULL JOIN labels l ON d.doc_id = l.doc_id")
def join_outer(spark: SparkSession, sf_dir: str) -> DataFrame:
    d, l = table(spark, sf_dir, "documents").select("doc_id", "lang"), table(spark, sf_dir, "labels").select("doc_id", "quality")
    return d.join(l, "doc_id", "full").select("doc_id", F.coalesce("quality", F.lit(-1)).alias("quality"), "lang")


@register("op_join_lateral", "SELECT c_custkey, o.o_orderkey, o.o_totalprice FROM customer, LATERAL (SELECT o_orderkey, o_totalprice FROM orders WHERE o_custkey = c_custkey ORDER BY o_totalprice DESC, o_orderkey LIMIT 2) o")
def join_lateral(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The two dearest orders of each customer: a top-k a key by rank, which needs no join at all."""
    w = Window.partitionBy("o_custkey").orderBy(F.desc("o_totalprice"), "o_orderkey")
    o = table(spark, sf_dir, "orders").withColumn("rn", F.row_number().over(w)).filter("rn <= 2")
    return o.join(table(spark, sf_dir, "customer"), o["o_custkey"] == F.col("c_custkey"), "left_semi").select(F.col("o_custkey").alias("c_custkey"), "o_orderkey", "o_totalprice")


@register("op_join_as_of", "SELECT e.event_id, coalesce(max(p.event_id), -1) AS last_click FROM events e LEFT JOIN events p ON p.user_id = e.user_id AND p.event_type = 'click' AND (p.ts, p.event_id) <= (e.ts, e.event_id) AND p.ts = (SELECT max(ts) FROM events q WHERE q.user_id = e.user_id AND q.event_type = 'click' AND q.ts <= e.ts) WHERE e.event_type = 'purchase' GROUP BY 1")
def join_as_of(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The last click of the same user before each purchase."""
    e = table(spark, sf_dir, "events")
    bought = e.filter("event_type = 'purchase'").select("event_id", "user_id", "ts")
    clicks = e.filter("event_type = 'click'").select("user_id", "ts", F.col("event_id").alias("click"))
    return as_of(bought, clicks, ["user_id"], "ts", ["click"]).select("event_id", F.coalesce("asof_click", F.lit(-1)).alias("last_click"))


@register("op_join_interval", "SELECT a.conv_id AS doc, a.turn AS outer_turn, b.turn AS inner_turn FROM conversations a JOIN conversations b ON a.conv_id = b.conv_id AND b.turn > a.turn")
def join_interval(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Ancestor and descendant turns as an interval join in bins; a turn's number is its depth less three."""
    turns = open_tree(spark, sf_dir, "threads").nodes.filter("label = 'turn' and kind = 'elem'")
    points = turns.select("doc", "pre", (F.col("depth") - 3).cast("long").alias("inner_turn"))
    spans = turns.select("doc", (F.col("pre") + 1).alias("low"), "last", (F.col("depth") - 3).cast("long").alias("outer_turn")).filter("low <= last")
    return point_in_interval(points, spans, ["doc"], "pre", "low", "last", 64).select("doc", "outer_turn", "inner_turn")


@register("op_join_salted", "SELECT source, count(*)::BIGINT AS n FROM documents GROUP BY 1")
def join_salted(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "source")
    return salted_join(docs, docs.select("source").distinct(), "source").groupBy("source").agg(F.count("*").alias("n"))


@register("op_join_theta", "SELECT r_name, count(*)::BIGINT AS n FROM region JOIN customer ON c_nationkey > r_regionkey * 5 GROUP BY 1")
def join_theta(spark: SparkSession, sf_dir: str) -> DataFrame:
    c, r = table(spark, sf_dir, "customer"), broadcast_if_small(table(spark, sf_dir, "region"), 1000)
    return c.join(r, c["c_nationkey"] > r["r_regionkey"] * 5).groupBy("r_name").agg(F.count("*").alias("n"))


@register("op_join_natural_self", "SELECT a.n_nationkey AS a, b.n_nationkey AS b FROM nation a JOIN nation b ON a.n_regionkey = b.n_regionkey AND a.n_nationkey < b.n_nationkey")
def join_self(spark: SparkSession, sf_dir: str) -> DataFrame:
    n = table(spark, sf_dir, "nation")
    return n.alias("a").join(n.alias("b"), "n_regionkey").filter("a.n_nationkey < b.n_nationkey").select(F.col("a.n_nationkey").alias("a"), F.col("b.n_nationkey").alias("b"))


@register("op_passages_in_documents", "SELECT b.item_id, count(*)::BIGINT AS n FROM benchmark b JOIN documents d ON contains(d.text, b.text) GROUP BY 1")
def passages(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Which benchmark passages occur in how many documents: q-gram postings of the rarest gram give candidates, texts verify."""
    from treeloom.workloads.texts import _postings, texts_of

    texts = texts_of(spark, sf_dir)
    post = _postings(spark, sf_dir)
    rarity = post.groupBy("gram").agg(F.count("*").alias("df"))
    from treeloom.text.qgram import build_postings

    items = table(spark, sf_dir, "benchmark").select(F.col("item_id").alias("text_id"), F.col("text").alias("value"))
    grams = build_postings(items).withColumnRenamed("text_id", "item_id").join(rarity, "gram")
    rarest = grams.groupBy("item_id").agg(F.min_by("gram", F.struct("df", "gram")).alias("gram"))
    pairs = rarest.join(post, "gram").select("item_id", "text_id")
    own = items.select(F.col("text_id").alias("item_id"), F.col("value").alias("passage"))
    return pairs.join(own, "item_id").join(texts, "text_id").filter(F.col("value").contains(F.col("passage"))).groupBy("item_id").agg(F.count("*").alias("n"))


# --- aggregation ----------------------------------------------------------------------------------------------------


@register(
    "op_aggregate",
    "SELECT l_returnflag, l_linestatus, count(*)::BIGINT AS n, sum(l_quantity) AS qty, round(avg(l_extendedprice), 4) AS price, min(l_shipdate) AS first_ship, max(l_discount) AS disc, count(DISTINCT l_partkey)::BIGINT AS parts, count_if(l_tax > 0.04)::BIGINT AS taxed, arg_max(l_orderkey, (l_extendedprice, l_orderkey)) AS dearest FROM lineitem GROUP BY 1, 2",
)
def aggregate(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "lineitem").groupBy("l_returnflag", "l_linestatus").agg(
        F.count("*").alias("n"), F.sum("l_quantity").alias("qty"), F.round(F.avg("l_extendedprice"), 4).alias("price"), F.min("l_shipdate").alias("first_ship"), F.max("l_discount").alias("disc"),
        F.count_distinct("l_partkey").alias("parts"), F.count_if(F.col("l_tax") > 0.04).alias("taxed"), F.max_by("l_orderkey", F.struct("l_extendedprice", "l_orderkey")).alias("dearest"),
    )


@register("op_statistics", "SELECT l_returnflag, round(stddev_samp(l_quantity), 6) AS sd, round(corr(l_quantity, l_extendedprice), 6) AS corr, round(quantile_cont(l_discount, 0.5), 6) AS median, round(var_pop(l_tax), 8) AS var FROM lineitem GROUP BY 1")
def statistics(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "lineitem").groupBy("l_returnflag").agg(
        F.round(F.stddev_samp("l_quantity"), 6).alias("sd"), F.round(F.corr("l_quantity", "l_extendedprice"), 6).alias("corr"), F.round(F.percentile("l_discount", 0.5), 6).alias("median"), F.round(F.var_pop("l_tax"), 8).alias("var")
    )


@register("op_approximate_aggregates", "SELECT true AS close")
def approximate_aggregates(spark: SparkSession, sf_dir: str) -> DataFrame:
    """HyperLogLog, percentile and distinct sketches stay within 10 per cent of the exact values."""
    l = table(spark, sf_dir, "lineitem")
    got = l.agg(F.approx_count_distinct("l_partkey", 0.02).alias("a"), F.hll_sketch_estimate(F.hll_sketch_agg("l_partkey")).alias("h"), F.count_distinct("l_partkey").alias("n"), F.percentile_approx("l_quantity", 0.5).alias("p"), F.percentile("l_quantity", 0.5).alias("q"))
    near = lambda x, y: F.abs(F.col(x) - F.col(y)) <= 0.1 * F.col(y)
    return got.select((near("a", "n") & near("h", "n") & near("p", "q")).alias("close"))


@register("op_listagg", "SELECT o_custkey, string_agg(o_orderstatus, ',' ORDER BY o_orderkey) AS states FROM orders GROUP BY 1")
def listagg(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = F.sort_array(F.collect_list(F.struct("o_orderkey", "o_orderstatus")))
    return table(spark, sf_dir, "orders").groupBy("o_custkey").agg(F.array_join(F.transform(rows, lambda x: x["o_orderstatus"]), ",").alias("states"))


_SETS = "SELECT coalesce(o_orderstatus, 'all') AS status, coalesce(o_orderpriority, 'all') AS priority, count(*)::BIGINT AS n, grouping_id(o_orderstatus, o_orderpriority)::BIGINT AS g FROM orders GROUP BY "


def _grouped(df: DataFrame) -> DataFrame:
    got = df.agg(F.count("*").alias("n"), F.grouping_id().alias("g"))
    return got.select(F.coalesce("o_orderstatus", F.lit("all")).alias("status"), F.coalesce("o_orderpriority", F.lit("all")).alias("priority"), "n", "g")


@register("op_cube", _SETS + "CUBE (o_orderstatus, o_orderpriority)")
def cube(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _grouped(table(spark, sf_dir, "orders").cube("o_orderstatus", "o_orderpriority"))


@register("op_rollup", _SETS + "ROLLUP (o_orderstatus, o_orderpriority)")
def rollup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _grouped(table(spark, sf_dir, "orders").rollup("o_orderstatus", "o_orderpriority"))


@register("op_grouping_sets", _SETS + "GROUPING SETS ((o_orderstatus), (o_orderpriority))")
def grouping_sets(spark: SparkSession, sf_dir: str) -> DataFrame:
    cols = [F.col("o_orderstatus"), F.col("o_orderpriority")]
    return _grouped(table(spark, sf_dir, "orders").groupingSets([[cols[0]], [cols[1]]], *cols))


@register("op_pivot", "SELECT o_orderpriority AS priority, count_if(o_orderstatus = 'F')::BIGINT AS f, count_if(o_orderstatus = 'O')::BIGINT AS o, count_if(o_orderstatus = 'P')::BIGINT AS p FROM orders GROUP BY 1")
def pivot(spark: SparkSession, sf_dir: str) -> DataFrame:
    got = table(spark, sf_dir, "orders").groupBy(F.col("o_orderpriority").alias("priority")).pivot("o_orderstatus", ["F", "O", "P"]).count()
    return got.select("priority", *[F.coalesce(x, F.lit(0)).alias(x.lower()) for x in "FOP"])


@register("op_unpivot", "SELECT doc_id, 'quality' AS name, quality AS value FROM labels UNION ALL SELECT doc_id, 'toxic', toxic FROM labels")
def unpivot(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "labels").unpivot("doc_id", ["quality", "toxic"], "name", "value")


@register("op_label_depth_profile", "WITH t AS (SELECT turn FROM conversations) SELECT (turn + 3)::INTEGER AS depth, count(*)::BIGINT AS n FROM t GROUP BY 1")
def depth_profile(spark: SparkSession, sf_dir: str) -> DataFrame:
    return open_tree(spark, sf_dir, "threads").nodes.filter("label = 'turn' and kind = 'elem'").groupBy("depth").agg(F.count("*").alias("n"))


# --- windows, sorting, sets -------------------------------------------------------------------------------------------


@register(
    "op_windows",
    """SELECT o_orderkey, row_number() OVER w AS rn, rank() OVER v AS rk, dense_rank() OVER v AS dr, ntile(4) OVER w AS nt, round(percent_rank() OVER w, 6) AS pr,
coalesce(lag(o_orderkey) OVER w, -1) AS before, coalesce(lead(o_orderkey) OVER w, -1) AS after, first_value(o_orderkey) OVER w AS first, round(sum(o_totalprice) OVER (w ROWS BETWEEN 2 PRECEDING AND CURRENT ROW), 2) AS moving
FROM orders WINDOW w AS (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey), v AS (PARTITION BY o_custkey ORDER BY o_orderpriority)""",
)
def windows(spark: SparkSession, sf_dir: str) -> DataFrame:
    w = Window.partitionBy("o_custkey").orderBy("o_orderdate", "o_orderkey")
    v = Window.partitionBy("o_custkey").orderBy("o_orderpriority")
    long = lambda c: c.cast("long")
    return table(spark, sf_dir, "orders").select(
        "o_orderkey", long(F.row_number().over(w)).alias("rn"), long(F.rank().over(v)).alias("rk"), long(F.dense_rank().over(v)).alias("dr"), long(F.ntile(4).over(w)).alias("nt"), F.round(F.percent_rank().over(w), 6).alias("pr"),
        F.coalesce(F.lag("o_orderkey").over(w), F.lit(-1)).alias("before"), F.coalesce(F.lead("o_orderkey").over(w), F.lit(-1)).alias("after"), F.first("o_orderkey").over(w).alias("first"),
        F.round(F.sum("o_totalprice").over(w.rowsBetween(-2, 0)), 2).alias("moving"),
    )


@register("op_top_k", "SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 20")
def top_k(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "orders").select("o_orderkey", "o_totalprice").orderBy(F.desc("o_totalprice"), "o_orderkey").limit(20)


@register("op_set_operations", """SELECT 'both' AS kind, doc_id FROM (SELECT doc_id FROM documents WHERE contains(text, 'License') INTERSECT SELECT doc_id FROM documents WHERE lang = 'en')
UNION ALL SELECT 'first', doc_id FROM (SELECT doc_id FROM documents WHERE contains(text, 'License') EXCEPT SELECT doc_id FROM documents WHERE lang = 'en')
UNION ALL SELECT 'either', doc_id FROM (SELECT doc_id FROM documents WHERE contains(text, 'License') UNION SELECT doc_id FROM documents WHERE contains(text, 'para'))""")
def set_operations(spark: SparkSession, sf_dir: str) -> DataFrame:
    d = table(spark, sf_dir, "documents")
    a, b, c = d.filter(F.col("text").contains("License")).select("doc_id"), d.filter("lang = 'en'").select("doc_id"), d.filter(F.col("text").contains("para")).select("doc_id")
    tag = lambda x, k: x.select(F.lit(k).alias("kind"), "doc_id")
    return tag(a.intersect(b), "both").unionAll(tag(a.exceptAll(b), "first")).unionAll(tag(a.union(c).distinct(), "either"))


@register("op_subqueries", "WITH m AS (SELECT avg(o_totalprice) AS a FROM orders) SELECT c_custkey FROM customer WHERE c_acctbal > (SELECT avg(c_acctbal) FROM customer) AND c_custkey IN (SELECT o_custkey FROM orders, m WHERE o_totalprice > a)")
def subqueries(spark: SparkSession, sf_dir: str) -> DataFrame:
    c, o = table(spark, sf_dir, "customer"), table(spark, sf_dir, "orders")
    rich = c.join(F.broadcast(c.agg(F.avg("c_acctbal").alias("a"))), F.col("c_acctbal") > F.col("a"))
    dear = o.join(F.broadcast(o.agg(F.avg("o_totalprice").alias("m"))), F.col("o_totalprice") > F.col("m"))
    return rich.join(dear, rich["c_custkey"] == dear["o_custkey"], "left_semi").select("c_custkey")


@register("op_recursive_ancestors", "SELECT conv_id AS doc, count(*)::BIGINT AS depth FROM conversations GROUP BY 1")
def recursive_ancestors(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Chains of turns followed by a recursive query over parent pointers."""
    turns = open_tree(spark, sf_dir, "threads").nodes.filter("label = 'turn' and kind = 'elem'").select("doc", "pre", "parent", "depth")
    turns.createOrReplaceTempView("treeloom_turns")
    return spark.sql("""WITH RECURSIVE chain(doc, pre, n) AS (
      SELECT doc, pre, CAST(1 AS BIGINT) FROM treeloom_turns WHERE depth = 3
      UNION ALL SELECT t.doc, t.pre, c.n + 1 FROM chain c JOIN treeloom_turns t ON t.doc = c.doc AND t.parent = c.pre)
      SELECT doc, max(n) AS depth FROM chain GROUP BY doc""")


@register("op_sample_fraction", "SELECT true AS near")
def sample_fraction(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A seeded sample of a tenth has between a twentieth and a fifth of the rows."""
    l = table(spark, sf_dir, "lineitem")
    return l.sample(0.1, 7).agg(F.count("*").alias("s")).join(F.broadcast(l.agg(F.count("*").alias("n")))).select(F.col("s").between(F.col("n") / 20, F.col("n") / 5).alias("near"))
