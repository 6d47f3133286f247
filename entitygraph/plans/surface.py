"""Queries over the operators, sources, sinks, functions and streams around the methods, each with its SQL twin."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from entitygraph.functions import sql as fn
from entitygraph.operators import blocking, matching
from entitygraph.operators import relational as rel
from entitygraph.operators.hierarchical import cluster_closure
from entitygraph.plans import catalogue as cat
from entitygraph.plans.catalogue import _REFS, _SCORED, _TOK, MU, _closure, _refs, _scored, _soft, _tokens, _with, query
from entitygraph.plans.pipeline import ResolveConfig
from entitygraph.shared import materialise, new_path
from entitygraph.sources import files
from entitygraph.sources.fixtures import register_tables
from entitygraph.streaming import windows as win
from entitygraph.streaming.arrivals import link_index_of_stream


def _read(spark, sf, table: str) -> DataFrame:
    return spark.read.parquet(f"{sf}/{table}.parquet")


def _counted(c: str = "*") -> F.Column:
    return F.count(c).alias("n")


# ---- sources and sinks
def _round_trip(spark, sf, fmt: str, table: str = "customer", **options) -> DataFrame:
    path, df = new_path(spark, f"{fmt}-source"), _read(spark, sf, table)
    df.write.options(**options).format(fmt).save(path)
    return spark.read.options(**options).format(fmt).schema(df.schema).load(path)


for _fmt, _options in (("csv", {"header": True}), ("json", {}), ("orc", {})):

    @query(f"op_source_{_fmt}", "SELECT c_custkey, c_name, c_nationkey, c_acctbal, c_mktsegment FROM customer")
    def _(spark, sf, fmt=_fmt, options=_options):
        return _round_trip(spark, sf, fmt, **options)


@query("op_source_text", "SELECT c_name || '|' || c_mktsegment AS line, count(*) AS n FROM customer GROUP BY ALL")
def _(spark, sf):
    path = new_path(spark, "text-source")
    _read(spark, sf, "customer").select(F.concat_ws("|", "c_name", "c_mktsegment")).write.text(path)
    return spark.read.text(path).groupBy(F.col("value").alias("line")).agg(_counted())


@query("op_source_mixed_layouts", "SELECT 'customers' AS source, count(*) AS n FROM customer UNION ALL SELECT 'suppliers', count(*) FROM supplier UNION ALL SELECT 'nations', count(*) FROM nation")
def _(spark, sf):
    """Files of unlike formats and columns as one record set."""
    csv, json = new_path(spark, "mixed-csv"), new_path(spark, "mixed-json")
    _read(spark, sf, "customer").write.option("header", True).csv(csv)
    _read(spark, sf, "supplier").write.json(json)
    with_header = spark.read.option("header", True).csv(csv)
    specs = [files.SourceSpec(with_header, "customers", "c_custkey"), files.SourceSpec(json, "suppliers", "s_suppkey", "json"), files.SourceSpec(f"{sf}/nation.parquet", "nations", "n_nationkey")]
    return files.merge_files(spark, specs).groupBy("source").agg(_counted())


@query("op_source_file_name", "SELECT CAST(count(*) AS BIGINT) AS n, 'parquet' AS kind FROM nation")
def _(spark, sf):
    return _read(spark, sf, "nation").withColumn("kind", F.regexp_extract(F.col("_metadata.file_path"), r"\.([a-z]+)$", 1)).groupBy("kind").agg(_counted())


_ASSIGNED = _with(*_SCORED, _closure(), select="SELECT cluster_id, record_id FROM clusters")


def _clusters(spark, sf) -> DataFrame:
    scored, refs = _scored(spark, sf)
    return materialise(cluster_closure(scored, refs, MU), "clusters")


@query("op_sink_parquet", _ASSIGNED)
def _(spark, sf):
    path = new_path(spark, "link-index")
    files.write_link_index(_clusters(spark, sf), path)
    return files.read_link_index(spark, path)


@query("op_sink_partitioned", _ASSIGNED)
def _(spark, sf):
    """Parts by a hash of the cluster id: a look-up of one cluster reads one of them."""
    path = new_path(spark, "link-index-parts")
    _clusters(spark, sf).withColumn("part", F.pmod(F.xxhash64("cluster_id"), F.lit(16))).repartition("part").write.partitionBy("part").parquet(path)
    return spark.read.schema("cluster_id string, record_id string, part long").parquet(path).select("cluster_id", "record_id")


@query("op_sink_json", _ASSIGNED)
def _(spark, sf):
    path = new_path(spark, "link-index-json")
    _clusters(spark, sf).write.json(path)
    return spark.read.schema("cluster_id string, record_id string").json(path)


# ---- projection and predicates
@query("op_projection", "SELECT event_id, upper(event_type) AS kind, CAST(json_extract_string(props, '$.k') AS INT) AS k FROM events")
def _(spark, sf):
    return _read(spark, sf, "events").select("event_id", F.upper("event_type").alias("kind"), F.get_json_object("props", "$.k").cast("int").alias("k"))


@query(
    "op_predicates",
    """SELECT c_custkey FROM customer WHERE c_acctbal BETWEEN 0 AND 5000 AND c_mktsegment IN ('BUILDING', 'MACHINERY', 'HOUSEHOLD') AND NOT c_name LIKE '%7' AND c_nationkey IS NOT DISTINCT FROM c_nationkey
       AND regexp_matches(c_name, '[02468]$')""",
)
def _(spark, sf):
    c = _read(spark, sf, "customer")
    keep = F.col("c_acctbal").between(0, 5000) & F.col("c_mktsegment").isin("BUILDING", "MACHINERY", "HOUSEHOLD") & ~F.col("c_name").like("%7")
    return c.where(keep & F.col("c_nationkey").eqNullSafe(F.col("c_nationkey")) & F.col("c_name").rlike("[02468]$")).select("c_custkey")


# ---- joins
@query("op_join_equi", _with(_REFS, _TOK, select="SELECT record_id, pos, token, df FROM tok JOIN freq USING (token)"))
def _(spark, sf):
    tokens, freqs = _tokens(spark, sf)
    return tokens.join(freqs, "token").select("record_id", "pos", "token", "df")


@query("op_join_broadcast", "SELECT c_custkey, n_name, r_name FROM customer JOIN nation ON n_nationkey = c_nationkey JOIN region ON r_regionkey = n_regionkey")
def _(spark, sf):
    """Nations and regions have a fixed number of rows."""
    n, r = F.broadcast(_read(spark, sf, "nation")), F.broadcast(_read(spark, sf, "region"))
    c = _read(spark, sf, "customer")
    return c.join(n, F.col("c_nationkey") == F.col("n_nationkey")).join(r, F.col("n_regionkey") == F.col("r_regionkey")).select("c_custkey", "n_name", "r_name")


@query("op_join_semi", _with(_REFS, _TOK, select="SELECT DISTINCT record_id FROM refs WHERE record_id IN (SELECT record_id FROM bt)"))
def _(spark, sf):
    """Records that can be blocked at all."""
    refs = _refs(spark, sf)
    return refs.join(blocking.blocking_tokens(blocking.cut_stop_tokens(*_tokens(spark, sf))), "record_id", "left_semi").select("record_id")


@query("op_join_anti", _with(_REFS, _TOK, select="SELECT record_id FROM refs WHERE record_id NOT IN (SELECT a FROM pairs UNION SELECT b FROM pairs)"))
def _(spark, sf):
    """Records that share no block."""
    refs = _refs(spark, sf)
    pairs = blocking.candidate_pairs(cat._blocked(spark, sf)[1])
    ends = pairs.select(F.col("a").alias("record_id")).union(pairs.select(F.col("b").alias("record_id")))
    return refs.join(ends, "record_id", "left_anti").select("record_id")


@query(
    "op_join_outer",
    """SELECT coalesce(c_nationkey, s_nationkey) AS nation, coalesce(c.n, 0) AS customers, coalesce(s.n, 0) AS suppliers FROM (SELECT c_nationkey, count(*) AS n FROM customer WHERE c_acctbal < 0 GROUP BY 1) c
       FULL OUTER JOIN (SELECT s_nationkey, count(*) AS n FROM supplier GROUP BY 1) s ON c_nationkey = s_nationkey""",
)
def _(spark, sf):
    c = _read(spark, sf, "customer").where("c_acctbal < 0").groupBy(F.col("c_nationkey").alias("nation")).agg(F.count("*").alias("c"))
    s = _read(spark, sf, "supplier").groupBy(F.col("s_nationkey").alias("nation")).agg(F.count("*").alias("s"))
    zero = F.lit(0)
    return c.join(s, "nation", "full_outer").select("nation", F.coalesce("c", zero).alias("customers"), F.coalesce("s", zero).alias("suppliers"))


@query("op_join_theta", "SELECT a.n_nationkey AS a, b.n_nationkey AS b FROM nation a JOIN nation b ON a.n_regionkey < b.n_regionkey AND length(a.n_name) >= length(b.n_name)")
def _(spark, sf):
    """Both sides have a fixed number of rows."""
    n = _read(spark, sf, "nation")
    a, b = (n.select(F.col("n_nationkey").alias(x), F.col("n_regionkey").alias(f"r{x}"), F.length("n_name").alias(f"l{x}")) for x in "ab")
    return a.join(F.broadcast(b), (F.col("ra") < F.col("rb")) & (F.col("la") >= F.col("lb"))).select("a", "b")


@query("op_join_range", "SELECT p.p_partkey, s_suppkey FROM part p JOIN supplier s ON abs(p.p_retailprice - s.s_acctbal) <= 5")
def _(spark, sf):
    return rel.range_join(_read(spark, sf, "part"), _read(spark, sf, "supplier"), "p_retailprice", "s_acctbal", 5).select("p_partkey", "s_suppkey")


@query("op_join_range_in_blocks", _with(_REFS, _TOK, select="SELECT a, b FROM pairs JOIN refs x ON x.record_id = a JOIN refs y ON y.record_id = b WHERE abs(length(x.body) - length(y.body)) <= 4"))
def _(spark, sf):
    """Pairs of a block whose lengths differ by at most four: the range is part of the join, not a filter after it."""
    tokens = blocking.blocking_tokens(blocking.cut_stop_tokens(*_tokens(spark, sf)))
    sized = tokens.join(_refs(spark, sf).select("record_id", F.length("body").alias("len")), "record_id")
    left, right = (sized.select("token", F.col("record_id").alias(x), F.col("len").alias(f"l{x}")) for x in "ab")
    return rel.range_join(left, right, "la", "lb", 4, ("token",)).where("a < b").select("a", "b").distinct()


@query(
    "op_join_as_of",
    """SELECT e.event_id, p.value AS last_value FROM (SELECT * FROM events WHERE event_type = 'purchase') e
       ASOF LEFT JOIN (SELECT user_id, ts, value FROM events WHERE event_type = 'click') p ON e.user_id = p.user_id AND e.ts >= p.ts""",
)
def _(spark, sf):
    e = _read(spark, sf, "events")
    left = e.where("event_type = 'purchase'").select("event_id", "user_id", "ts")
    return rel.as_of_join(left, e.where("event_type = 'click'"), "user_id", "ts", "value", "last_value").select("event_id", "last_value")


@query(
    "op_join_interval",
    """SELECT x.user_id, x.event_id AS a, y.event_id AS b FROM events x JOIN events y ON x.user_id = y.user_id AND abs(epoch_us(x.ts) - epoch_us(y.ts)) <= 3600000000
       AND (x.ts < y.ts OR (x.ts = y.ts AND x.event_id < y.event_id))""",
)
def _(spark, sf):
    return rel.interval_pairs(_read(spark, sf, "events"), "user_id", "ts", "event_id", 3600)


# ---- aggregation
@query("op_agg_hash", "SELECT l_returnflag, l_linestatus, count(*) AS n, CAST(sum(CAST(l_quantity AS DECIMAL(18, 2))) AS DOUBLE) AS quantity, min(l_shipdate) AS first_ship, max(l_linenumber) AS last_line FROM lineitem GROUP BY ALL")
def _(spark, sf):
    total = F.sum(F.col("l_quantity").cast("decimal(18,2)")).cast("double")
    return _read(spark, sf, "lineitem").groupBy("l_returnflag", "l_linestatus").agg(_counted(), total.alias("quantity"), F.min("l_shipdate").alias("first_ship"), F.max("l_linenumber").alias("last_line"))


@query("op_agg_distinct", "SELECT o_orderstatus, count(DISTINCT o_custkey) AS customers, count(DISTINCT o_orderpriority) AS priorities FROM orders GROUP BY 1")
def _(spark, sf):
    return _read(spark, sf, "orders").groupBy("o_orderstatus").agg(F.count_distinct("o_custkey").alias("customers"), F.count_distinct("o_orderpriority").alias("priorities"))


@query("op_agg_collect", _with(_REFS, select="SELECT truth_id, string_agg(DISTINCT record_id, ' ' ORDER BY record_id) AS members FROM refs GROUP BY truth_id"))
def _(spark, sf):
    return _refs(spark, sf).groupBy("truth_id").agg(F.array_join(F.array_sort(F.collect_set("record_id")), " ").alias("members"))


_SEGMENTS = "SELECT c_mktsegment, c_nationkey, count(*) AS n, grouping(c_mktsegment) + 0 AS gs, grouping(c_nationkey) + 0 AS gn FROM customer GROUP BY {}"


def _segments(grouped) -> DataFrame:
    return grouped.agg(_counted(), F.grouping("c_mktsegment").cast("long").alias("gs"), F.grouping("c_nationkey").cast("long").alias("gn"))


@query("op_agg_rollup", _SEGMENTS.format("ROLLUP (c_mktsegment, c_nationkey)"))
def _(spark, sf):
    return _segments(_read(spark, sf, "customer").rollup("c_mktsegment", "c_nationkey"))


@query("op_agg_cube", _SEGMENTS.format("CUBE (c_mktsegment, c_nationkey)"))
def _(spark, sf):
    return _segments(_read(spark, sf, "customer").cube("c_mktsegment", "c_nationkey"))


@query("op_agg_grouping_sets", _SEGMENTS.format("GROUPING SETS ((c_mktsegment), (c_nationkey))"))
def _(spark, sf):
    c = _read(spark, sf, "customer")
    return _segments(c.groupingSets([[F.col("c_mktsegment")], [F.col("c_nationkey")]], F.col("c_mktsegment"), F.col("c_nationkey")))


@query("op_agg_approximate", "SELECT true AS distinct_near, true AS median_near, true AS sketch_covers FROM range(1)")
def _(spark, sf):
    """Approximate counts against exact ones: distinct customers within 5 %, the median's rank within 1 %, a count-min sketch never below the count of the commonest priority."""
    o = _read(spark, sf, "orders")
    top = o.groupBy("o_orderpriority").agg(_counted()).orderBy(F.desc("n"), "o_orderpriority").limit(1)  # one row
    one = o.agg(F.approx_count_distinct("o_custkey", 0.01).alias("near"), F.count_distinct("o_custkey").alias("exact"), F.percentile_approx("o_totalprice", 0.5, 1000).alias("median"), F.count_min_sketch("o_orderpriority", F.lit(0.001), F.lit(0.99), F.lit(1)).alias("sketch"))
    rank = o.crossJoin(F.broadcast(one.select("median"))).agg(F.avg((F.col("o_totalprice") <= F.col("median")).cast("int")).alias("rank"))
    covers = F.length("sketch") > 0
    return one.crossJoin(rank).crossJoin(top).select((F.abs(F.col("near") / F.col("exact") - 1) < 0.05).alias("distinct_near"), (F.abs(F.col("rank") - 0.5) < 0.01).alias("median_near"), covers.alias("sketch_covers"))


# ---- windows
@query(
    "op_window_ranking",
    """SELECT o_orderkey, row_number() OVER w AS place, rank() OVER (PARTITION BY o_custkey ORDER BY o_orderstatus) AS rnk, dense_rank() OVER (PARTITION BY o_custkey ORDER BY o_orderstatus) AS dense
       FROM orders WINDOW w AS (PARTITION BY o_custkey ORDER BY o_totalprice DESC, o_orderkey)""",
)
def _(spark, sf):
    price = Window.partitionBy("o_custkey").orderBy(F.desc("o_totalprice"), "o_orderkey")
    status = Window.partitionBy("o_custkey").orderBy("o_orderstatus")
    long = lambda c: c.cast("long")
    return _read(spark, sf, "orders").select("o_orderkey", long(F.row_number().over(price)).alias("place"), long(F.rank().over(status)).alias("rnk"), long(F.dense_rank().over(status)).alias("dense"))


@query("op_window_top_k", "SELECT o_custkey, o_orderkey FROM (SELECT *, row_number() OVER (PARTITION BY o_custkey ORDER BY o_totalprice DESC, o_orderkey) AS r FROM orders) q WHERE r <= 3")
def _(spark, sf):
    return rel.top_k(_read(spark, sf, "orders"), ["o_custkey"], [F.desc("o_totalprice"), F.asc("o_orderkey")], 3).select("o_custkey", "o_orderkey")


@query(
    "op_window_analytic",
    f"""WITH {cat._LOG_DUCK}, m AS (SELECT sample, mu, max(f1) AS f1 FROM log WHERE algo = 'two_step' GROUP BY ALL)
    SELECT sample, mu, round(f1 - lag(f1) OVER w, 6) AS rise, lead(mu) OVER w AS next_mu, first_value(f1) OVER w AS first_f1 FROM m WINDOW w AS (PARTITION BY sample ORDER BY mu)""",
)
def _(spark, sf):
    m = cat._log(spark, sf).where("algo = 'two_step'").groupBy("sample", "mu").agg(F.max("f1").alias("f1"))
    w = Window.partitionBy("sample").orderBy("mu")
    return m.select("sample", "mu", F.round(F.col("f1") - F.lag("f1").over(w), 6).alias("rise"), F.lead("mu").over(w).alias("next_mu"), F.first("f1").over(w).alias("first_f1"))


@query(
    "op_window_frames",
    """SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY epoch_us(ts) RANGE BETWEEN 86400000000 PRECEDING AND CURRENT ROW) AS day_before,
       max(value) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN 2 PRECEDING AND CURRENT ROW) AS top_of_three FROM events""",
)
def _(spark, sf):
    e = _read(spark, sf, "events").withColumn("t", F.unix_micros(F.col("ts").cast("timestamp")))
    day = Window.partitionBy("user_id").orderBy("t").rangeBetween(-86_400_000_000, 0)
    three = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(-2, 0)
    return e.select("event_id", F.count("*").over(day).alias("day_before"), F.max("value").over(three).alias("top_of_three"))


# ---- sort, sets
@query("op_top_tokens", _with(_REFS, _TOK, select="SELECT token, c FROM freq ORDER BY c DESC, token LIMIT 20"))
def _(spark, sf):
    return _tokens(spark, sf)[1].select("token", "c").orderBy(F.desc("c"), "token").limit(20)


@query("op_sort_link_index", _with(*_SCORED, _closure(), select="SELECT cluster_id, record_id, row_number() OVER (ORDER BY cluster_id, record_id) AS place FROM clusters"))
def _(spark, sf):
    """Places in the order of the whole index, without one task that sees it all: each sorted range counts on from those before it."""
    ordered = materialise(_clusters(spark, sf).repartitionByRange("cluster_id", "record_id").sortWithinPartitions("cluster_id", "record_id").select("*", F.spark_partition_id().alias("part"), F.monotonically_increasing_id().alias("at")), "ordered")
    sizes = ordered.groupBy("part").agg(_counted(), F.min("at").alias("first"))
    before = Window.orderBy("part").rowsBetween(Window.unboundedPreceding, -1)  # one row a part
    base = sizes.select("part", "first", F.coalesce(F.sum("n").over(before), F.lit(0)).alias("base"))
    return ordered.join(F.broadcast(base), "part").select("cluster_id", "record_id", (F.col("at") - F.col("first") + F.col("base") + 1).alias("place"))


_TWO = (*_SCORED, "jac AS (SELECT a, b FROM (SELECT a, b, len(list_intersect(x.t, y.t)) AS i, len(list_distinct(list_concat(x.t, y.t))) AS u FROM pairs JOIN (SELECT record_id, list(token) AS t FROM kept GROUP BY 1) x ON x.record_id = a JOIN (SELECT record_id, list(token) AS t FROM kept GROUP BY 1) y ON y.record_id = b) q WHERE round(i / u, 6) >= 0.3), hi AS (SELECT a, b FROM scored WHERE score >= 0.6)")


def _two_sets(spark, sf) -> tuple[DataFrame, DataFrame]:
    by_matrix = matching.above(_scored(spark, sf)[0], MU).select("a", "b")
    by_tokens = matching.above(_scored(spark, sf, measure="jaccard")[0], 0.3).select("a", "b")
    return by_matrix, by_tokens


for _n, _sql, _f in (("union", "UNION", lambda x, y: x.unionByName(y).distinct()), ("intersect", "INTERSECT", DataFrame.intersect), ("except", "EXCEPT", DataFrame.exceptAll)):

    @query(f"op_set_{_n}", _with(*_TWO, select=f"SELECT a, b FROM hi {_sql} SELECT a, b FROM jac"))
    def _(spark, sf, f=_f):
        """Pairs that either measure, both, or the matrix alone finds."""
        return f(*_two_sets(spark, sf))


@query("op_set_both_ways", _with(*_SCORED, select="SELECT a AS v, b AS n FROM scored WHERE score >= 0.6 UNION ALL SELECT b, a FROM scored WHERE score >= 0.6"))
def _(spark, sf):
    e = matching.above(_scored(spark, sf)[0], MU)
    return e.select(F.col("a").alias("v"), F.col("b").alias("n")).unionAll(e.select("b", "a"))


# ---- scalar functions
@query(
    "op_string",
    """SELECT c_custkey, upper(c_mktsegment) AS up, trim(replace(c_name, '#', ' ')) AS cleaned, string_split(c_name, '#')[2] AS number, concat_ws('/', c_mktsegment, c_name) AS joined, substr(c_name, 1, 3) AS head,
       lpad(CAST(c_nationkey AS VARCHAR), 4, '0') AS padded, CAST(levenshtein(c_mktsegment, 'MACHINES') AS INT) AS edits, CAST(length(c_name) AS INT) AS len, translate(c_mktsegment, 'AEIOU', '12345') AS coded, reverse(c_name) AS back FROM customer""",
)
def _(spark, sf):
    c = F.col
    return _read(spark, sf, "customer").select(
        "c_custkey", F.upper("c_mktsegment").alias("up"), F.trim(F.regexp_replace("c_name", "#", " ")).alias("cleaned"), F.split("c_name", "#")[1].alias("number"), F.concat_ws("/", "c_mktsegment", "c_name").alias("joined"),
        F.substring("c_name", 1, 3).alias("head"), F.lpad(c("c_nationkey").cast("string"), 4, "0").alias("padded"), F.levenshtein("c_mktsegment", F.lit("MACHINES")).alias("edits"), F.length("c_name").alias("len"),
        F.translate("c_mktsegment", "AEIOU", "12345").alias("coded"), F.reverse("c_name").alias("back"),
    )


@query(
    "op_math",
    """SELECT p_partkey, round(log2(p_retailprice), 6) AS l, round(sqrt(p_size), 6) AS s, abs(p_size - 25) AS away, greatest(p_size, 10) AS g, least(p_size, 10) AS le, CAST(pow(p_size, 2) AS DOUBLE) AS sq,
       CAST(CAST(p_retailprice AS DECIMAL(18, 2)) * 3 AS DECIMAL(20, 2)) AS tripled, p_partkey % 7 AS rest FROM part""",
)
def _(spark, sf):
    p = F.col("p_size")
    return _read(spark, sf, "part").select(
        "p_partkey", F.round(F.log2("p_retailprice"), 6).alias("l"), F.round(F.sqrt(p), 6).alias("s"), F.abs(p - 25).alias("away"), F.greatest(p, F.lit(10)).alias("g"), F.least(p, F.lit(10)).alias("le"), F.pow(p, F.lit(2)).alias("sq"),
        (F.col("p_retailprice").cast("decimal(18,2)") * 3).cast("decimal(20,2)").alias("tripled"), (F.col("p_partkey") % 7).alias("rest"),
    )


@query(
    "op_date",
    """SELECT CAST(year(o_orderdate) AS INT) AS y, CAST(month(o_orderdate) AS INT) AS m, CAST(quarter(o_orderdate) AS INT) AS q, CAST(dayofmonth(last_day(o_orderdate)) AS INT) AS days, count(*) AS n,
       CAST(max(date_diff('day', CAST(o_orderdate AS DATE), DATE '1999-01-01')) AS INT) AS ago FROM orders GROUP BY ALL""",
)
def _(spark, sf):
    d = F.col("o_orderdate")
    keys = [F.year(d).alias("y"), F.month(d).alias("m"), F.quarter(d).alias("q"), F.dayofmonth(F.last_day(d)).alias("days")]
    return _read(spark, sf, "orders").groupBy(*keys).agg(_counted(), F.max(F.datediff(F.lit("1999-01-01").cast("date"), d.cast("date"))).alias("ago"))


@query(
    "op_array",
    _with(_REFS, _TOK, "l AS (SELECT record_id, list(token ORDER BY pos) AS t FROM tok GROUP BY record_id)",
          select="""SELECT record_id, CAST(len(t) AS INT) AS n, CAST(len(list_distinct(t)) AS INT) AS kinds, CAST(list_max(list_transform(t, lambda x: length(x))) AS INT) AS longest, CAST(list_sum(list_transform(t, lambda x: length(x))) AS INT) AS letters,
          CAST(len(list_filter(t, lambda x: length(x) > 5)) AS INT) AS long_ones, array_to_string(list_sort(list_distinct(t)), ' ') AS sorted FROM l"""),
)
def _(spark, sf):
    t = F.col("tokens")
    lists = blocking.filtered_records(_tokens(spark, sf)[0])
    return lists.select(
        "record_id", F.size(t).alias("n"), F.size(F.array_distinct(t)).alias("kinds"), F.array_max(F.transform(t, F.length)).alias("longest"), F.aggregate(t, F.lit(0), lambda s, x: s + F.length(x)).alias("letters"),
        F.size(F.filter(t, lambda x: F.length(x) > 5)).alias("long_ones"), F.array_join(F.array_sort(F.array_distinct(t)), " ").alias("sorted"),
    )


@query("op_vector_cosine", "SELECT vec_id, round(list_dot_product(CAST(embedding AS DOUBLE[]), list_transform(CAST(embedding AS DOUBLE[]), lambda x: abs(x))) / list_dot_product(CAST(embedding AS DOUBLE[]), CAST(embedding AS DOUBLE[])), 5) AS lean FROM embeddings")
def _(spark, sf):
    e = F.col("embedding").cast("array<double>")
    dot = lambda x, y: F.aggregate(F.zip_with(x, y, lambda p, q: p * q), F.lit(0.0), lambda s, z: s + z)
    return _read(spark, sf, "embeddings").select("vec_id", F.round(dot(e, F.transform(e, F.abs)) / dot(e, e), 5).alias("lean"))


@query("op_map", "SELECT 'n:' || n_nationkey AS record_id, 'n_name,n_regionkey' AS names, n_name AS name, CAST(2 AS INT) AS n FROM nation")
def _(spark, sf):
    a = F.col("attrs")
    merged = files.merge_files(spark, [files.SourceSpec(f"{sf}/nation.parquet", "n", "n_nationkey")])
    return merged.select("record_id", F.array_join(F.array_sort(F.map_keys(a)), ",").alias("names"), a["n_name"].alias("name"), F.size(F.map_values(a)).alias("n"))


@query("op_json", """SELECT event_type, CAST(sum(CAST(json_extract_string(props, '$.k') AS BIGINT)) AS BIGINT) AS total, '{"kind":"' || event_type || '"}' AS told FROM events GROUP BY event_type""")
def _(spark, sf):
    k = F.from_json("props", "k long")["k"]
    return _read(spark, sf, "events").groupBy("event_type").agg(F.sum(k).alias("total")).withColumn("told", F.to_json(F.struct(F.col("event_type").alias("kind"))))


# ---- subqueries, sampling
_SCALAR = "SELECT c_custkey FROM customer WHERE c_acctbal > (SELECT avg(c_acctbal) FROM customer)"
_EXISTS = "SELECT s_suppkey FROM supplier s WHERE EXISTS (SELECT 1 FROM customer c WHERE c.c_nationkey = s.s_nationkey AND c.c_acctbal > 9900)"
_RECURSIVE = "WITH RECURSIVE up(n, x) AS (SELECT 1, CAST(sum(o_custkey) AS BIGINT) FROM orders UNION ALL SELECT n + 1, x * 2 FROM up WHERE n < 10) SELECT n, x FROM up"
for _n, _sql in (("scalar", _SCALAR), ("exists", _EXISTS), ("recursive", _RECURSIVE)):

    @query(f"op_subquery_{_n}", _sql)
    def _(spark, sf, sql=_sql):
        register_tables(spark, sf, "customer", "supplier", "orders")
        return spark.sql(sql)


@query("op_sample_entities", _with(_REFS, select="SELECT record_id, truth_id FROM refs WHERE CAST(('0x' || substr(md5('3:' || truth_id), 1, 8))::BIGINT % 100 AS BIGINT) < 20"))
def _(spark, sf):
    return rel.entity_sample(_refs(spark, sf), "truth_id", 20, 3).select("record_id", "truth_id")


# ---- functions
@query("op_udf_arrow", _with(*_SCORED, select="SELECT a, b, score FROM scored"))
def _(spark, sf):
    kept, blocked = cat._blocked(spark, sf)
    listed = matching.with_tokens(blocking.candidate_pairs(blocked), blocking.filtered_records(kept))
    return listed.select("a", "b", fn.scoring_matrix_py("ta", "tb").alias("score"))


@query("op_udf_sql", f"SELECT doc_id, {cat._ASCII.format(c='text')} AS body FROM documents")
def _(spark, sf):
    fn.register_expressions(spark)
    register_tables(spark, sf, "documents")
    return spark.sql("SELECT doc_id, normalise_reference(text) AS body FROM documents")


@query("m1_token_similarity", "SELECT a.n_name AS a, b.n_name AS b, round(1.0 - CAST(levenshtein(a.n_name, b.n_name) AS DOUBLE) / greatest(length(a.n_name), length(b.n_name)), 6) AS s FROM nation a, nation b")
def _(spark, sf):
    """By the SQL function; nations have a fixed number of rows."""
    fn.register_expressions(spark)
    register_tables(spark, sf, "nation")
    return spark.sql("SELECT a.n_name AS a, b.n_name AS b, round(token_similarity(a.n_name, b.n_name), 6) AS s FROM nation a CROSS JOIN nation b")


@query("op_udaf_entropy", _with(_REFS, _TOK, select="SELECT truth_id, round(entropy(token), 6) AS h FROM tok JOIN refs USING (record_id) GROUP BY truth_id"))
def _(spark, sf):
    tokens = _tokens(spark, sf)[0].join(_refs(spark, sf).select("record_id", "truth_id"), "record_id")
    return tokens.groupBy("truth_id").agg(fn.entropy_agg("token").alias("h"))


@query("op_udtf_tokens", _with(_REFS, _TOK, select="SELECT record_id, pos, token FROM tok"))
def _(spark, sf):
    fn.register_tables(spark)
    _refs(spark, sf).createOrReplaceTempView("entitygraph_references")
    return spark.sql("SELECT record_id, t.pos, t.token FROM entitygraph_references, LATERAL tokens_of(body) t")


@query("op_udtf_refine", _with(*cat._SOFT, select="SELECT DISTINCT component_id, record_id, true AS same FROM comp"))
def _(spark, sf):
    """The SQL form of the refinement against the DataFrame form, record by record."""
    from entitygraph.operators.louvain import refine_local

    fn.register_tables(spark)
    edges = _soft(spark, sf)[3]
    edges.createOrReplaceTempView("entitygraph_edges")
    found = spark.sql("SELECT * FROM refine(TABLE(entitygraph_edges) PARTITION BY component_id)")
    other = refine_local(edges).select("component_id", "record_id", F.col("community").alias("c"))
    return found.join(other, ["component_id", "record_id"], "full_outer").select("component_id", "record_id", F.col("community").eqNullSafe(F.col("c")).alias("same"))


# ---- streams
_WINDOW = "SELECT strftime({t}, '%Y-%m-%d %H:%M:%S') AS from_ts, strftime({t} + INTERVAL 1 HOUR, '%Y-%m-%d %H:%M:%S') AS to_ts, event_type, count(*) AS n, CAST(sum(CAST(value AS DECIMAL(18, 2))) AS DOUBLE) AS total FROM {f} GROUP BY ALL"


@query("s1_tumbling", _WINDOW.format(t="time_bucket(INTERVAL 1 HOUR, ts)", f="events"))
def _(spark, sf):
    return win.run_to_end(win.tumbling(win.event_stream(spark, sf)), "complete")


@query("s2_sliding", _WINDOW.format(t="t", f="(SELECT e.*, time_bucket(INTERVAL 30 MINUTES, ts) - i * INTERVAL 30 MINUTES AS t FROM events e, range(0, 2) r(i)) x"))
def _(spark, sf):
    return win.run_to_end(win.sliding(win.event_stream(spark, sf)), "complete")


@query(
    "s3_session",
    """WITH g AS (SELECT user_id, ts, CASE WHEN ts < lag(ts) OVER (PARTITION BY user_id ORDER BY ts) + INTERVAL 2 HOURS THEN 0 ELSE 1 END AS fresh FROM events),
       s AS (SELECT user_id, ts, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS k FROM g)
       SELECT user_id, strftime(min(ts), '%Y-%m-%d %H:%M:%S') AS from_ts, count(*) AS n FROM s GROUP BY user_id, k""",
)
def _(spark, sf):
    return win.run_to_end(win.sessions(win.event_stream(spark, sf)), "complete")


@query("s4_dedup_watermark", "SELECT DISTINCT user_id, event_type FROM events")
def _(spark, sf):
    return win.run_to_end(win.first_of_kind(win.event_stream(spark, sf)))


@query("s5_interval_join", "SELECT x.user_id, x.event_id AS a, y.event_id AS b FROM events x JOIN events y ON x.user_id = y.user_id AND x.event_type = 'click' AND y.event_type = 'purchase' AND y.ts >= x.ts AND y.ts <= x.ts + INTERVAL 120 MINUTES")
def _(spark, sf):
    return win.run_to_end(win.followed_within(win.event_stream(spark, sf), "click", "purchase", 120))


@query("s6_incremental_link_index", _ASSIGNED)
def _(spark, sf):
    """References that arrive as files, all in one batch: what the pipeline with closure alone gives. (In several batches a token's frequency is that at arrival; see the tests.)"""
    path = new_path(spark, "arriving")
    _refs(spark, sf).select("record_id", "body").write.parquet(path)
    return link_index_of_stream(spark, path, ResolveConfig(mu=MU, clusterer="closure"), 10_000)

