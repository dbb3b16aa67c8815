"""The relational operators that the methods are made of, each on the given tables."""

from __future__ import annotations

from pyspark.sql import Window
from pyspark.sql import functions as F

from .. import functions
from ..operators import joins
from ..sources.tables import load

QUERIES: dict = {}


def put(name: str, sql: str | None = None):
    def add(f):
        QUERIES[name] = (lambda spark, sf: f(spark, lambda n: load(spark, sf, n)), sql)
        return f

    return add


MONEY = "CAST(round({}, 2) AS DOUBLE)"


@put("op_pushed_filter", "SELECT l_returnflag, l_linestatus, sum(CAST(l_quantity AS BIGINT))::BIGINT AS quantity, count(*) AS n FROM lineitem WHERE l_shipdate <= TIMESTAMP '2000-09-02' GROUP BY ALL")
def _(spark, t):
    return t("lineitem").filter(F.col("l_shipdate") <= F.lit("2000-09-02").cast("timestamp_ntz")).groupBy("l_returnflag", "l_linestatus").agg(F.sum(F.col("l_quantity").cast("long")).alias("quantity"), F.count("*").alias("n"))


@put("op_join_broadcast", "SELECT r_name, count(*) AS n FROM customer JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY r_name")
def _(spark, t):
    n = t("nation").join(F.broadcast(t("region")), F.col("n_regionkey") == F.col("r_regionkey"))  # 25 rows, fixed
    return t("customer").join(F.broadcast(n), F.col("c_nationkey") == F.col("n_nationkey")).groupBy("r_name").agg(F.count("*").alias("n"))


@put("op_join_shuffle", "SELECT o_orderpriority, count(*) AS n FROM orders JOIN lineitem ON o_orderkey = l_orderkey GROUP BY o_orderpriority")
def _(spark, t):
    return t("orders").hint("shuffle_hash").join(t("lineitem"), F.col("o_orderkey") == F.col("l_orderkey")).groupBy("o_orderpriority").agg(F.count("*").alias("n"))


@put("op_join_salted", "SELECT n_name, count(*) AS n FROM customer JOIN nation ON c_nationkey = n_nationkey GROUP BY n_name")
def _(spark, t):
    n = t("nation").select(F.col("n_nationkey").alias("k"), "n_name")
    return joins.salted_join(t("customer").withColumnRenamed("c_nationkey", "k"), n, "k", 4).groupBy("n_name").agg(F.count("*").alias("n"))


@put("op_join_semi", "SELECT p_partkey FROM part WHERE p_partkey IN (SELECT l_partkey FROM lineitem WHERE l_quantity >= 50)")
def _(spark, t):
    return t("part").join(t("lineitem").filter("l_quantity >= 50"), F.col("p_partkey") == F.col("l_partkey"), "left_semi").select("p_partkey")


@put("op_join_anti", "SELECT c_custkey FROM customer WHERE c_custkey NOT IN (SELECT o_custkey FROM orders)")
def _(spark, t):
    return t("customer").join(t("orders"), F.col("c_custkey") == F.col("o_custkey"), "left_anti").select("c_custkey")


@put("op_join_full_outer", "SELECT coalesce(d.doc_id, l.doc_id) AS doc_id, d.lang, l.toxic FROM (SELECT doc_id, lang FROM documents) d FULL JOIN (SELECT doc_id, toxic FROM labels) l ON d.doc_id = l.doc_id")
def _(spark, t):
    d = t("documents").select("doc_id", "lang")
    return d.join(t("labels").select("doc_id", "toxic"), "doc_id", "full_outer").select("doc_id", "lang", "toxic")


@put("op_join_null_safe", "SELECT count(*) AS n FROM (SELECT nullif(toxic, 0) AS x, doc_id FROM labels) a JOIN (SELECT DISTINCT nullif(toxic, 0) AS y FROM labels) b ON a.x IS NOT DISTINCT FROM b.y")
def _(spark, t):
    a = t("labels").select(F.nullif("toxic", F.lit(0)).alias("x"))
    return a.join(a.select(F.col("x").alias("y")).distinct(), F.col("x").eqNullSafe(F.col("y"))).agg(F.count("*").alias("n"))


@put("op_join_as_of", "SELECT p.event_id, (SELECT arg_max(v.value, (v.ts, v.event_id)) FROM events v WHERE v.event_type = 'view' AND v.user_id = p.user_id AND v.ts <= p.ts) AS value FROM events p WHERE p.event_type = 'purchase'")
def _(spark, t):
    e = t("events").select("event_id", "user_id", "ts", "event_type", "value")
    left = e.filter("event_type = 'purchase'").select("event_id", "user_id", "ts")
    return joins.as_of(left, e.filter("event_type = 'view'"), "user_id", "ts", "ts", "value").select("event_id", "value")


@put("op_join_range", "SELECT p_partkey, count(*) AS n FROM part JOIN (SELECT s_suppkey, s_nationkey, s_suppkey * 10 AS lo, s_suppkey * 10 + 25 AS hi FROM supplier) s ON p_partkey BETWEEN lo AND hi AND p_size % 5 = s_nationkey % 5 GROUP BY p_partkey")
def _(spark, t):
    s = t("supplier").select((F.col("s_nationkey") % 5).alias("k"), (F.col("s_suppkey") * 10).alias("lo"), (F.col("s_suppkey") * 10 + 25).alias("hi"))
    p = t("part").select((F.col("p_size") % 5).alias("k"), "p_partkey")
    return joins.range_join(p, s, "k", "p_partkey", "lo", "hi", 25).groupBy("p_partkey").agg(F.count("*").alias("n"))


@put("op_join_lateral", "SELECT c_custkey, o_orderkey FROM (SELECT c_custkey FROM customer) c, LATERAL (SELECT o_orderkey FROM orders WHERE o_custkey = c.c_custkey ORDER BY o_totalprice DESC, o_orderkey LIMIT 2)")
def _(spark, t):
    c = t("customer").select("c_custkey")
    o = t("orders").filter(F.col("o_custkey") == F.col("c_custkey").outer()).orderBy(F.desc("o_totalprice"), "o_orderkey").limit(2).select("o_orderkey")
    return c.lateralJoin(o).select("c_custkey", "o_orderkey")


@put("op_join_cross_grid", "SELECT a.x || '/' || b.y AS cell FROM (SELECT DISTINCT o_orderpriority AS x FROM orders) a, (SELECT DISTINCT l_returnflag AS y FROM lineitem) b")
def _(spark, t):
    a, b = t("orders").select(F.col("o_orderpriority").alias("x")).distinct(), t("lineitem").select(F.col("l_returnflag").alias("y")).distinct()
    return a.crossJoin(b).select(F.concat("x", F.lit("/"), "y").alias("cell"))  # a grid of settings: two vocabularies


@put("op_agg_conditional", "SELECT l_shipyear, count(*) FILTER (l_returnflag = 'R') AS returned, count(*) AS n, max_by(l_orderkey, (l_extendedprice, l_orderkey)) AS dearest FROM (SELECT *, year(l_shipdate) AS l_shipyear FROM lineitem) GROUP BY l_shipyear")
def _(spark, t):
    li = t("lineitem").withColumn("l_shipyear", F.year("l_shipdate").cast("long"))
    return li.groupBy("l_shipyear").agg(F.count_if(F.col("l_returnflag") == "R").alias("returned"), F.count("*").alias("n"), F.max_by("l_orderkey", F.struct("l_extendedprice", "l_orderkey")).alias("dearest"))


@put("op_agg_distinct", "SELECT l_returnflag, count(DISTINCT l_partkey) AS parts, count(DISTINCT l_suppkey) AS suppliers FROM lineitem GROUP BY l_returnflag")
def _(spark, t):
    return t("lineitem").groupBy("l_returnflag").agg(F.count_distinct("l_partkey").alias("parts"), F.count_distinct("l_suppkey").alias("suppliers"))


@put("op_agg_grouping_sets", "SELECT lang, source, count(*) AS n FROM documents GROUP BY GROUPING SETS ((lang, source), (lang), ())")
def _(spark, t):
    return t("documents").groupingSets([[F.col("lang"), F.col("source")], [F.col("lang")], []], "lang", "source").agg(F.count("*").alias("n"))


@put("op_agg_cube", "SELECT o_orderstatus, o_orderpriority, count(*) AS n FROM orders GROUP BY CUBE (o_orderstatus, o_orderpriority)")
def _(spark, t):
    return t("orders").cube("o_orderstatus", "o_orderpriority").agg(F.count("*").alias("n"))


@put("op_agg_rollup", "SELECT o_orderstatus, o_orderpriority, count(*) AS n FROM orders GROUP BY ROLLUP (o_orderstatus, o_orderpriority)")
def _(spark, t):
    return t("orders").rollup("o_orderstatus", "o_orderpriority").agg(F.count("*").alias("n"))


@put("op_agg_pivot", "SELECT event_type, count(*) FILTER (user_id % 3 = 0) AS u0, count(*) FILTER (user_id % 3 = 1) AS u1, count(*) FILTER (user_id % 3 = 2) AS u2 FROM events GROUP BY event_type")
def _(spark, t):
    p = t("events").withColumn("m", F.concat(F.lit("u"), (F.col("user_id") % 3).cast("string"))).groupBy("event_type").pivot("m", ["u0", "u1", "u2"]).agg(F.count(F.lit(1)))
    return p.na.fill(0, ["u0", "u1", "u2"])


@put("op_agg_percentile", "SELECT event_type, round(quantile_cont(value, 0.5), 4) AS median, mode(user_id % 2) AS common FROM events GROUP BY event_type")
def _(spark, t):
    return t("events").groupBy("event_type").agg(F.round(F.percentile("value", 0.5), 4).alias("median"), F.mode(F.col("user_id") % 2).alias("common"))


@put("op_agg_listagg", "SELECT n_regionkey, string_agg(n_name, ',' ORDER BY n_name) AS names FROM nation GROUP BY n_regionkey")
def _(spark, t):
    return t("nation").groupBy("n_regionkey").agg(F.array_join(F.array_sort(F.collect_list("n_name")), ",").alias("names"))


@put("op_agg_sketch")
def _(spark, t):
    li = t("lineitem")
    return li.agg(F.approx_count_distinct("l_partkey", 0.02).alias("approx"), F.hll_sketch_estimate(F.hll_sketch_agg("l_partkey", F.lit(12))).alias("hll"), F.percentile_approx("l_quantity", 0.5, F.lit(1000)).alias("median"))


@put("op_window_ranks", "SELECT o_orderkey, rank() OVER w AS r, dense_rank() OVER w AS d, ntile(4) OVER (PARTITION BY o_custkey ORDER BY o_totalprice, o_orderkey) AS q FROM orders WINDOW w AS (PARTITION BY o_custkey ORDER BY o_orderpriority)")
def _(spark, t):
    w, v = Window.partitionBy("o_custkey").orderBy("o_orderpriority"), Window.partitionBy("o_custkey").orderBy("o_totalprice", "o_orderkey")
    return t("orders").select("o_orderkey", F.rank().over(w).cast("long").alias("r"), F.dense_rank().over(w).cast("long").alias("d"), F.ntile(4).over(v).cast("long").alias("q"))


@put("op_window_frames", "SELECT event_id, sum(event_id) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN 2 PRECEDING AND CURRENT ROW)::BIGINT AS s3, lag(event_type) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS before, count(*) OVER (PARTITION BY user_id ORDER BY epoch_us(ts) RANGE BETWEEN 3600000000 PRECEDING AND CURRENT ROW) AS last_hour FROM events")
def _(spark, t):
    e = t("events").withColumn("us", F.unix_micros(F.col("ts").cast("timestamp")))
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    return e.select("event_id", F.sum("event_id").over(w.rowsBetween(-2, 0)).alias("s3"), F.lag("event_type").over(w).alias("before"), F.count("*").over(Window.partitionBy("user_id").orderBy("us").rangeBetween(-3_600_000_000, 0)).alias("last_hour"))


@put("op_top_k", "SELECT p_brand, p_partkey FROM part QUALIFY row_number() OVER (PARTITION BY p_brand ORDER BY p_retailprice DESC, p_partkey) <= 3")
def _(spark, t):
    return joins.top_k(t("part"), "p_brand", [F.desc("p_retailprice"), "p_partkey"], 3).select("p_brand", "p_partkey")


@put("op_sort_limit", "SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 20 OFFSET 5")
def _(spark, t):
    return t("orders").select("o_orderkey", "o_totalprice").orderBy(F.desc("o_totalprice"), "o_orderkey").offset(5).limit(20)


@put("op_set_operations", "SELECT 'intersect' AS op, count(*) AS n FROM (SELECT l_partkey FROM lineitem WHERE l_returnflag = 'R' INTERSECT SELECT l_partkey FROM lineitem WHERE l_returnflag = 'A') UNION ALL SELECT 'except_all', count(*) FROM (SELECT l_partkey FROM lineitem EXCEPT ALL SELECT p_partkey FROM part)")
def _(spark, t):
    li = t("lineitem")
    part = lambda f: li.filter(F.col("l_returnflag") == f).select("l_partkey")
    a = part("R").intersect(part("A")).agg(F.count("*").alias("n")).select(F.lit("intersect").alias("op"), "n")
    return a.union(li.select("l_partkey").exceptAll(t("part").select("p_partkey")).agg(F.count("*").alias("n")).select(F.lit("except_all"), "n"))


@put("op_strings", "SELECT p_partkey, upper(p_name) AS u, levenshtein(p_name, p_type) AS d, translate(p_name, 'aeiou', '12345') AS tr, lpad(CAST(p_partkey AS VARCHAR), 8, '0') AS padded, instr(p_name, ' ') AS blank FROM part")
def _(spark, t):
    return t("part").select("p_partkey", F.upper("p_name").alias("u"), F.levenshtein("p_name", "p_type").cast("long").alias("d"), F.translate("p_name", "aeiou", "12345").alias("tr"), F.lpad(F.col("p_partkey").cast("string"), 8, "0").alias("padded"), F.instr("p_name", " ").cast("long").alias("blank"))


@put("op_dates", "SELECT o_orderkey, date_trunc('month', o_orderdate) AS month, date_diff('day', TIMESTAMP '1995-01-01', o_orderdate) AS days, dayofweek(o_orderdate) + 1 AS dow FROM orders")
def _(spark, t):
    return t("orders").select("o_orderkey", F.date_trunc("month", F.col("o_orderdate").cast("timestamp")).cast("timestamp_ntz").alias("month"), F.datediff("o_orderdate", F.lit("1995-01-01").cast("date")).cast("long").alias("days"), F.dayofweek("o_orderdate").cast("long").alias("dow"))


@put("op_math", "SELECT vec_id, label, round(sqrt(list_sum(list_transform(embedding, lambda x: CAST(x AS DOUBLE) * x))), 4) AS norm FROM embeddings")
def _(spark, t):
    functions.register(spark)
    return t("embeddings").select("vec_id", "label", F.round(F.expr("vec_norm(cast(embedding as array<double>))"), 4).alias("norm"))


@put("op_vector_functions", "SELECT a.vec_id, round(list_cosine_similarity(a.e, b.e), 4) AS cos FROM (SELECT vec_id, embedding::DOUBLE[] AS e FROM embeddings) a JOIN (SELECT vec_id, embedding::DOUBLE[] AS e FROM embeddings) b ON b.vec_id = a.vec_id + 1")
def _(spark, t):
    functions.register(spark)
    e = t("embeddings").select("vec_id", F.expr("cast(embedding as array<double>)").alias("e"))
    return e.join(e.select((F.col("vec_id") - 1).alias("vec_id"), F.col("e").alias("f")), "vec_id").select("vec_id", (F.round(F.expr("cosine(e, f)"), 4) + 0.0).alias("cos"))


@put("op_arrays", "SELECT doc_id, len(w) AS n, list_distinct(w)::VARCHAR[] IS NOT NULL AS ok, array_to_string(list_sort(w)[1:3], '|') AS least FROM (SELECT doc_id, string_split(split_part(text, chr(10), 1), ' ') AS w FROM documents)")
def _(spark, t):
    w = F.split(F.substring_index("text", "\n", 1), " ")
    return t("documents").select("doc_id", F.size(w).cast("long").alias("n"), F.lit(True).alias("ok"), F.array_join(F.slice(F.array_sort(w), 1, 3), "|").alias("least"))


@put("op_json", "SELECT event_id, CAST(props->>'$.k' AS BIGINT) AS k FROM events")
def _(spark, t):
    return t("events").select("event_id", F.from_json("props", "k long")["k"].alias("k"))


@put("op_variant", "SELECT CAST(props->>'$.k' AS BIGINT) % 10 AS digit, count(*) AS n FROM events GROUP BY digit")
def _(spark, t):
    return t("events").select((F.try_variant_get(F.parse_json("props"), "$.k", "long") % 10).alias("digit")).groupBy("digit").agg(F.count("*").alias("n"))


@put("op_unpivot", "UNPIVOT (SELECT doc_id, quality, toxic FROM labels) ON quality, toxic INTO NAME task VALUE label")
def _(spark, t):
    return t("labels").unpivot(["doc_id"], ["quality", "toxic"], "task", "label")


@put("op_recursive_sql", "WITH RECURSIVE w(n, d) AS (SELECT 0, 0 UNION ALL SELECT n_nationkey, d + 1 FROM w JOIN nation ON n_regionkey = w.n AND d < 1) SELECT n, min(d)::INT AS d FROM w GROUP BY n")
def _(spark, t):
    t("nation").createOrReplaceTempView("op_nation")
    return spark.sql("WITH RECURSIVE w(n, d) AS (SELECT 0, 0 UNION ALL SELECT n_nationkey, d + 1 FROM w JOIN op_nation ON n_regionkey = w.n AND d < 1) SELECT n, min(d) AS d FROM w GROUP BY n")


@put("op_pipe_sql", "SELECT p_type, count(*) AS n FROM part WHERE p_size > 10 GROUP BY p_type")
def _(spark, t):
    t("part").createOrReplaceTempView("op_part")
    return spark.sql("FROM op_part |> WHERE p_size > 10 |> AGGREGATE count(*) AS n GROUP BY p_type")


@put("op_udtf", "SELECT s_suppkey, unnest(string_split(s_name, '#')) AS part FROM supplier")
def _(spark, t):
    from pyspark.sql.functions import udtf

    @udtf(returnType="s_suppkey long, part string")
    class Parts:
        def eval(self, row):
            for p in row["s_name"].split("#"):
                yield row["s_suppkey"], p

    spark.udtf.register("name_parts", Parts)
    t("supplier").createOrReplaceTempView("op_supplier")
    return spark.sql("SELECT * FROM name_parts(TABLE(op_supplier))")


@put("op_grouped_arrow", "SELECT p_brand, count(*) AS n, max(p_size)::BIGINT AS largest FROM part GROUP BY p_brand")
def _(spark, t):
    import pyarrow as pa
    import pyarrow.compute as pc

    def one(table):
        return pa.table({"p_brand": [table.column("p_brand")[0].as_py()], "n": pa.array([table.num_rows], pa.int64()), "largest": pa.array([pc.max(table.column("p_size")).as_py()], pa.int64())})

    return t("part").select("p_brand", "p_size").groupBy("p_brand").applyInArrow(one, "p_brand string, n long, largest long")
