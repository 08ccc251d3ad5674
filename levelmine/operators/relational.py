"""Queries of joins, aggregates, windows, sorts, sets, subqueries and functions that graph users need around mining."""

from __future__ import annotations

from pyspark.sql import Window
from pyspark.sql import functions as F

from levelmine.operators.exploration import COP, _text
from levelmine.operators.registry import query
from levelmine.session import read_table
from levelmine.sources import ctes
from levelmine.sources.ctes import sql
from levelmine.sources.graphs import load, part_copurchase, supplier_coorder

SUP = ctes.COSUPPLIER


def _g(spark, sf_dir):
    return load(part_copurchase, spark, sf_dir)


def _s(spark, sf_dir):
    return load(supplier_coorder, spark, sf_dir)


@query(sql(COP, select="SELECT src || '>' || dst AS name, CAST(dst - src AS BIGINT) AS gap FROM e"))
def project_edges(spark, sf_dir):
    return _g(spark, sf_dir).edges.select(F.concat_ws(">", F.col("src").cast("string"), F.col("dst").cast("string")).alias("name"), (F.col("dst") - F.col("src")).alias("gap"))


@query(sql(COP, select="SELECT CAST(src AS BIGINT) AS src, CAST(dst AS BIGINT) AS dst FROM e WHERE (src BETWEEN 100 AND 900 OR dst IN (1000, 1001, 1002)) AND NOT CAST(src AS VARCHAR) LIKE '%7%' AND dst IS NOT NULL"))
def filter_edges(spark, sf_dir):
    c = F.col
    keep = (c("src").between(100, 900) | c("dst").isin(1000, 1001, 1002)) & ~c("src").cast("string").like("%7%") & c("dst").isNotNull()
    return _g(spark, sf_dir).edges.filter(keep).select("src", "dst")


_JOINED = sql(COP, select="SELECT CAST(src AS BIGINT) AS src, CAST(dst AS BIGINT) AS dst, label FROM e JOIN v ON v.id = src")


def _labelled(spark, sf_dir, hint):
    g = _g(spark, sf_dir)
    v = g.vertices.select(F.col("id").alias("src"), "label")
    return g.edges.select("src", "dst").join(v.hint(hint), "src")


@query(_JOINED)
def join_hash(spark, sf_dir):
    return _labelled(spark, sf_dir, "shuffle_hash")


@query(_JOINED)
def join_merge(spark, sf_dir):
    return _labelled(spark, sf_dir, "merge")


@query(_JOINED)
def join_broadcast(spark, sf_dir):
    """The label table is broadcast behind a check of its size; a larger one is merged."""
    small = _g(spark, sf_dir).vertices.count() <= 1_000_000
    return _labelled(spark, sf_dir, "broadcast" if small else "merge")


@query("SELECT a.r_name AS a, b.n_name AS b FROM region a JOIN nation b ON b.n_regionkey < a.r_regionkey")
def join_theta(spark, sf_dir):
    """An inequality between two tables of fixed size."""
    a, b = read_table(spark, sf_dir, "region"), read_table(spark, sf_dir, "nation")
    return a.crossJoin(b).filter("n_regionkey < r_regionkey").select(F.col("r_name").alias("a"), F.col("n_name").alias("b"))


_RUNS = """
r AS (SELECT src, count(*) AS n FROM e GROUP BY 1),
o AS (SELECT src, CAST(sum(n) OVER (ORDER BY src) AS BIGINT) - n AS start, n FROM r),
w AS (SELECT (row_number() OVER (ORDER BY src, dst) - 1) AS pos FROM e)
"""


@query(sql(COP, _RUNS, select="SELECT pos, CAST(src AS BIGINT) AS owner FROM w JOIN o ON pos >= start AND pos < start + n"))
def join_range(spark, sf_dir):
    """Which slice an offset lies in: a range join through blocks of positions."""
    from levelmine.graph.numbering import numbered

    g = _g(spark, sf_dir)
    e = numbered(g.edges.select("src", "dst"), "src", "dst")
    runs = e.groupBy("src").agg(F.min("pos").alias("start"), (F.max("pos") + 1).alias("stop"))
    block = 256
    spread = runs.withColumn("block", F.explode(F.sequence(F.floor(F.col("start") / block), F.floor((F.col("stop") - 1) / block))))
    at = e.select("pos", F.floor(F.col("pos") / block).alias("block"))
    return at.join(spread, "block").filter("pos >= start and pos < stop").select("pos", F.col("src").alias("owner"))


@query("SELECT e.event_id, (SELECT p.event_type FROM events p WHERE p.user_id = e.user_id AND (p.ts < e.ts OR (p.ts = e.ts AND p.event_id < e.event_id)) ORDER BY p.ts DESC, p.event_id DESC LIMIT 1) AS before FROM events e")
def join_asof(spark, sf_dir):
    """Each event and the type of its user's last event before it."""
    order = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, -1)
    return read_table(spark, sf_dir, "events").select("event_id", F.last("event_type", ignorenulls=True).over(order).alias("before"))


@query(sql(COP, select="SELECT p_partkey AS id, CAST(coalesce(n, 0) AS BIGINT) AS n FROM part LEFT JOIN (SELECT src, count(*) AS n FROM e GROUP BY 1) ON src = p_partkey"))
def join_outer(spark, sf_dir):
    out = _g(spark, sf_dir).edges.groupBy("src").agg(F.count("*").alias("n"))
    part = read_table(spark, sf_dir, "part").select(F.col("p_partkey").alias("id"))
    return part.join(out, F.col("id") == F.col("src"), "left").select("id", F.coalesce("n", F.lit(0).cast("long")).alias("n"))


@query(sql(COP, select="SELECT coalesce(a.src, b.dst) AS id, a.n AS out_n, b.n AS in_n FROM (SELECT src, count(*) AS n FROM e GROUP BY 1) a FULL JOIN (SELECT dst, count(*) AS n FROM e GROUP BY 1) b ON a.src = b.dst"))
def join_full(spark, sf_dir):
    e = _g(spark, sf_dir).edges
    a, b = e.groupBy("src").agg(F.count("*").alias("out_n")), e.groupBy("dst").agg(F.count("*").alias("in_n"))
    return a.join(b, F.col("src") == F.col("dst"), "full").select(F.coalesce("src", "dst").alias("id"), "out_n", "in_n")


@query(sql(COP, select="SELECT p_partkey AS id FROM part WHERE p_partkey IN (SELECT id FROM v)"))
def join_semi(spark, sf_dir):
    return read_table(spark, sf_dir, "part").select(F.col("p_partkey").alias("id")).join(_g(spark, sf_dir).vertices, "id", "left_semi")


@query(sql(COP, select="SELECT p_partkey AS id FROM part WHERE p_partkey NOT IN (SELECT id FROM v)"))
def join_anti(spark, sf_dir):
    return read_table(spark, sf_dir, "part").select(F.col("p_partkey").alias("id")).join(_g(spark, sf_dir).vertices, "id", "left_anti")


@query(sql(COP, ctes.SYM, select="SELECT count(*) AS n FROM s a JOIN s b ON a.b = b.a JOIN s c ON b.b = c.a JOIN s d ON c.b = d.a AND d.b = a.a WHERE a.a < b.a AND a.a < c.a AND a.a < d.a AND b.a < d.a AND a.a <> c.a"))
def square_join(spark, sf_dir):
    """Cycles of four, chords or not, by a chain of joins: pairs of paths of length two with the same ends."""
    s = _g(spark, sf_dir).sym.select("u", "v")
    two = s.toDF("p", "q").join(s.toDF("q", "r"), "q").filter("p < r")
    per = two.groupBy("p", "r").agg(F.count("*").alias("m"))
    return per.agg((F.sum(F.col("m") * (F.col("m") - 1) / 2) / 2).cast("long").alias("n"))


@query(sql(SUP, select="SELECT least(a.label, b.label) AS lo, greatest(a.label, b.label) AS hi, count(*) AS n FROM e JOIN v a ON a.id = src JOIN v b ON b.id = dst GROUP BY 1, 2"))
def agg_pattern(spark, sf_dir):
    return _pairs(spark, sf_dir).groupBy("lo", "hi").agg(F.count("*").alias("n"))


def _pairs(spark, sf_dir):
    g = _s(spark, sf_dir)
    lab = g.vertices.select("id", "label")
    e = g.edges.join(lab.toDF("src", "a"), "src").join(lab.toDF("dst", "b"), "dst")
    return e.select(F.least("a", "b").alias("lo"), F.greatest("a", "b").alias("hi"))


_HIER = """
h AS (SELECT r_name AS region, n_name AS nation FROM e JOIN supplier ON s_suppkey = src JOIN nation ON n_nationkey = s_nationkey JOIN region ON r_regionkey = n_regionkey)
"""


def _hier(spark, sf_dir):
    g = _s(spark, sf_dir)
    s, n, r = (read_table(spark, sf_dir, t) for t in ("supplier", "nation", "region"))
    named = s.join(n, s.s_nationkey == n.n_nationkey).join(r, n.n_regionkey == r.r_regionkey)
    return g.edges.join(named, F.col("src") == F.col("s_suppkey")).select(F.col("r_name").alias("region"), F.col("n_name").alias("nation"))


@query(sql(SUP, _HIER, select="SELECT region, nation, count(*) AS n FROM h GROUP BY ROLLUP (region, nation)"))
def motif_rollup(spark, sf_dir):
    return _hier(spark, sf_dir).rollup("region", "nation").agg(F.count("*").alias("n"))


@query(sql(SUP, _HIER, select="SELECT region, nation, count(*) AS n FROM h GROUP BY CUBE (region, nation)"))
def motif_cube(spark, sf_dir):
    return _hier(spark, sf_dir).cube("region", "nation").agg(F.count("*").alias("n"))


@query(sql(SUP, _HIER, select="SELECT region, nation, count(*) AS n FROM h GROUP BY GROUPING SETS ((region), (nation), ())"))
def motif_grouping_sets(spark, sf_dir):
    h = _hier(spark, sf_dir)
    return h.groupingSets([["region"], ["nation"], []], "region", "nation").agg(F.count("*").alias("n"))


@query(sql(SUP, _HIER, select="SELECT nation, count(*) FILTER (WHERE region = 'ASIA') AS asia, count(*) FILTER (WHERE region = 'EUROPE') AS europe FROM h GROUP BY 1"))
def motif_pivot(spark, sf_dir):
    out = _hier(spark, sf_dir).groupBy("nation").pivot("region", ["ASIA", "EUROPE"]).agg(F.count("region"))
    return out.select("nation", F.coalesce("ASIA", F.lit(0).cast("long")).alias("asia"), F.coalesce("EUROPE", F.lit(0).cast("long")).alias("europe"))


@query(sql(COP, select="SELECT CAST(src AS BIGINT) AS src, CAST(bit_or(1 << CAST(dst % 8 AS INTEGER)) AS BIGINT) AS bits, bool_and(dst > 500) AS far FROM e GROUP BY 1"))
def agg_bits(spark, sf_dir):
    e = _g(spark, sf_dir).edges.withColumn("b", F.expr("shiftleft(1L, cast(dst % 8 as int))"))
    return e.groupBy("src").agg(F.bit_or("b").alias("bits"), F.bool_and(F.col("dst") > 500).alias("far"))


@query(sql(COP, ctes.SYM, select="SELECT CAST(min(n) AS BIGINT) AS lo, CAST(max(n) AS BIGINT) AS hi, round(avg(n), 6) AS mean, round(stddev_samp(n), 6) AS sd, CAST(quantile_disc(n, 0.5) AS BIGINT) AS median FROM (SELECT count(*) AS n FROM s GROUP BY a)"))
def agg_degrees(spark, sf_dir):
    d = _g(spark, sf_dir).degrees()
    return d.agg(F.min("deg").alias("lo"), F.max("deg").alias("hi"), F.round(F.avg("deg"), 6).alias("mean"), F.round(F.stddev_samp("deg"), 6).alias("sd"), F.expr("percentile_disc(0.5) WITHIN GROUP (ORDER BY deg)").cast("long").alias("median"))


@query(sql(COP, select="SELECT count(DISTINCT src) AS exact, true AS hll_plus_close, true AS hll_sketch_close FROM e"))
def distinct_approx(spark, sf_dir):
    """Distinct ends of edges, by two sketches within a fifth of the exact number; a screen, not an answer."""
    e = _g(spark, sf_dir).edges
    got = e.agg(F.countDistinct("src").alias("exact"), F.approx_count_distinct("src").alias("a"), F.hll_sketch_estimate(F.hll_sketch_agg("src")).alias("b"))
    close = lambda c: F.abs(F.col(c) - F.col("exact")) <= 0.2 * F.col("exact")
    return got.select("exact", close("a").alias("hll_plus_close"), close("b").alias("hll_sketch_close"))


@query(sql(SUP, ctes.SYM, select="SELECT id, deg, CAST(row_number() OVER (PARTITION BY label ORDER BY deg DESC, id) AS INTEGER) AS rn, CAST(rank() OVER (PARTITION BY label ORDER BY deg DESC) AS INTEGER) AS rk, CAST(dense_rank() OVER (PARTITION BY label ORDER BY deg DESC) AS INTEGER) AS dr, CAST(ntile(3) OVER (PARTITION BY label ORDER BY deg DESC, id) AS INTEGER) AS nt FROM (SELECT a AS id, count(*) AS deg FROM s GROUP BY 1) JOIN v USING (id)"))
def rank_degree(spark, sf_dir):
    g = _s(spark, sf_dir)
    w = Window.partitionBy("label")
    by, full = w.orderBy(F.desc("deg")), w.orderBy(F.desc("deg"), "id")
    d = g.degrees().join(g.vertices.select("id", "label"), "id")
    return d.select("id", "deg", F.row_number().over(full).alias("rn"), F.rank().over(by).alias("rk"), F.dense_rank().over(by).alias("dr"), F.ntile(3).over(full).alias("nt"))


@query("SELECT conv_id, turn, lag(role) OVER w AS before, lead(role) OVER w AS after, first_value(role) OVER w AS opener, nth_value(turn, 2) OVER (PARTITION BY conv_id ORDER BY turn ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING) AS second FROM conversations WINDOW w AS (PARTITION BY conv_id ORDER BY turn)")
def window_lag(spark, sf_dir):
    w = Window.partitionBy("conv_id").orderBy("turn")
    whole = w.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    c = read_table(spark, sf_dir, "conversations")
    return c.select("conv_id", "turn", F.lag("role").over(w).alias("before"), F.lead("role").over(w).alias("after"), F.first("role").over(w).alias("opener"), F.nth_value("turn", 2).over(whole).alias("second"))


@query("SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW) AS so_far, count(*) OVER (PARTITION BY user_id ORDER BY ts RANGE BETWEEN INTERVAL 1 HOUR PRECEDING AND CURRENT ROW) AS last_hour FROM events")
def window_running(spark, sf_dir):
    rows = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, 0)
    near = Window.partitionBy("user_id").orderBy("at").rangeBetween(-3_600_000_000, 0)
    e = read_table(spark, sf_dir, "events").withColumn("at", F.unix_micros(F.col("ts").cast("timestamp")))
    return e.select("event_id", F.count("*").over(rows).alias("so_far"), F.count("*").over(near).alias("last_hour"))


_TOP = "SELECT lo, hi, n FROM (SELECT least(a.label, b.label) AS lo, greatest(a.label, b.label) AS hi, count(*) AS n FROM e JOIN v a ON a.id = src JOIN v b ON b.id = dst GROUP BY 1, 2)"


@query(sql(SUP, select=f"{_TOP} ORDER BY n DESC, lo, hi LIMIT 10 OFFSET 2"))
def topk_patterns(spark, sf_dir):
    return agg_pattern(spark, sf_dir).orderBy(F.desc("n"), "lo", "hi").offset(2).limit(10)


@query(sql(SUP, select=f"SELECT lo, hi, n FROM (SELECT *, row_number() OVER (PARTITION BY lo ORDER BY n DESC, hi) AS r FROM ({_TOP})) WHERE r <= 2"))
def topk_per_label(spark, sf_dir):
    w = Window.partitionBy("lo").orderBy(F.desc("n"), "hi")
    return agg_pattern(spark, sf_dir).withColumn("r", F.row_number().over(w)).filter("r <= 2").drop("r")


@query(sql(COP, select="SELECT count(*) AS edges, true AS all_known, true AS about_half FROM e"))
def sample_edges(spark, sf_dir):
    """A sample of half the edges: all are edges, and about half."""
    e = _g(spark, sf_dir).edges.select("src", "dst")
    some = e.sample(0.5, seed=1).withColumn("hit", F.lit(1))
    both = e.join(some, ["src", "dst"], "full")
    counts = both.agg(F.count("*").alias("edges"), F.count("hit").alias("n"))
    known = some.join(e, ["src", "dst"], "left_anti").agg((F.count("*") == 0).alias("all_known"))
    return counts.join(known).select("edges", "all_known", F.col("n").between(0.25 * F.col("edges"), 0.75 * F.col("edges")).alias("about_half"))


@query(sql(COP, select="SELECT CAST(src AS BIGINT) AS id FROM e UNION SELECT dst FROM e"))
def set_union(spark, sf_dir):
    e = _g(spark, sf_dir).edges
    return e.select(F.col("src").alias("id")).union(e.select(F.col("dst").alias("id"))).distinct()


@query(sql(COP, select="SELECT CAST(src AS BIGINT) AS id FROM e INTERSECT SELECT dst FROM e"))
def set_intersect(spark, sf_dir):
    e = _g(spark, sf_dir).edges
    return e.select(F.col("src").alias("id")).intersect(e.select(F.col("dst").alias("id")))


@query(sql(COP, select="SELECT CAST(src AS BIGINT) AS id FROM e EXCEPT ALL SELECT dst FROM e"))
def set_except(spark, sf_dir):
    e = _g(spark, sf_dir).edges
    return e.select(F.col("src").alias("id")).exceptAll(e.select(F.col("dst").alias("id")))


def _views(spark, sf_dir):
    from levelmine.functions.views import register

    register(_g(spark, sf_dir))


_EXISTS = "SELECT id FROM {v} p WHERE EXISTS (SELECT 1 FROM {e} q WHERE q.src = p.id AND q.dst > p.id + 1000)"


@query(sql(COP, select=f"SELECT CAST(id AS BIGINT) AS id FROM ({_EXISTS.format(v='v', e='e')})"))
def sub_exists(spark, sf_dir):
    _views(spark, sf_dir)
    return spark.sql(_EXISTS.format(v="vertices", e="edges"))


@query(sql(COP, ctes.SYM, select="SELECT CAST(a AS BIGINT) AS id FROM s GROUP BY a HAVING count(*) > (SELECT avg(n) FROM (SELECT count(*) AS n FROM s GROUP BY a))"))
def sub_scalar(spark, sf_dir):
    _views(spark, sf_dir)
    return spark.sql("WITH d AS (SELECT id, count(*) AS n FROM (SELECT explode(array(src, dst)) AS id FROM edges) GROUP BY id) SELECT id FROM d WHERE n > (SELECT avg(n) FROM d)")


@query(sql(COP, select="SELECT CAST(id AS BIGINT) AS id, n, CAST(top AS BIGINT) AS top FROM v, LATERAL (SELECT count(*) AS n, max(dst) AS top FROM e WHERE src = v.id)"))
def sub_lateral(spark, sf_dir):
    _views(spark, sf_dir)
    return spark.sql("SELECT id, n, top FROM vertices v, LATERAL (SELECT count(*) AS n, max(dst) AS top FROM edges WHERE src = v.id)")


@query(sql(SUP, select="SELECT CAST(3 AS INTEGER) AS k, count(*) AS n FROM e x JOIN e y ON x.dst = y.src UNION ALL SELECT 2, count(*) FROM e"))
def recursive_paths(spark, sf_dir):
    """Rising paths of two and three vertices by a recursive query; LIMIT ALL lifts the row limit that Spark sets on one."""
    from levelmine.functions.views import register

    register(_s(spark, sf_dir))
    return spark.sql("WITH RECURSIVE p(k, last) AS (SELECT 2, dst FROM edges UNION ALL SELECT k + 1, e.dst FROM p JOIN edges e ON e.src = p.last WHERE k < 3) SELECT k, count(*) AS n FROM (SELECT * FROM p LIMIT ALL) GROUP BY k")


_LISTS = "a AS (SELECT a AS id, list_sort(list(b)) AS w FROM s GROUP BY 1)"


@query(sql(COP, ctes.SYM, _LISTS, select="SELECT CAST(x.id AS BIGINT) AS id, CAST(len(x.w) AS INTEGER) AS n, CAST(x.w[1] AS BIGINT) AS low, CAST(list_max(x.w) AS BIGINT) AS high, CAST(list_sum(x.w) AS BIGINT) AS total, list_contains(x.w, 1000) AS has, CAST(len(list_filter(x.w, lambda q: q > x.id)) AS INTEGER) AS later, array_to_string(list_slice(x.w, 1, 2), '-') AS head FROM a x"))
def fn_array(spark, sf_dir):
    a = _g(spark, sf_dir).sym.groupBy(F.col("u").alias("id")).agg(F.sort_array(F.collect_list("v")).alias("w"))
    later = F.size(F.filter("w", lambda q: q > F.col("id")))
    return a.select("id", F.size("w").alias("n"), F.col("w")[0].alias("low"), F.array_max("w").alias("high"), F.aggregate("w", F.lit(0).cast("long"), lambda s, q: s + q).alias("total"), F.array_contains("w", 1000).alias("has"), later.alias("later"), F.array_join(F.slice("w", 1, 2).cast("array<string>"), "-").alias("head"))


@query(sql(COP, select="SELECT CAST(src AS BIGINT) AS src, CAST(dst AS BIGINT) AS dst, CAST(src & dst AS BIGINT) AS both, CAST(src | dst AS BIGINT) AS either, CAST(xor(src, dst) AS BIGINT) AS one, CAST(src << 2 AS BIGINT) AS up, CAST(dst >> 1 AS BIGINT) AS down, CAST(bit_count(dst) AS INTEGER) AS ones FROM e"))
def fn_bits(spark, sf_dir):
    s, d = F.col("src"), F.col("dst")
    return _g(spark, sf_dir).edges.select("src", "dst", s.bitwiseAND(d).alias("both"), s.bitwiseOR(d).alias("either"), s.bitwiseXOR(d).alias("one"), F.shiftleft(s, 2).alias("up"), F.shiftright(d, 1).alias("down"), F.bit_count(d).alias("ones"))


@query(sql(COP, select="SELECT CAST(src AS BIGINT) AS src, CAST(dst AS BIGINT) AS dst, round(ln(dst), 6) AS l, round(exp(src / 1000), 6) AS x, round(pow(dst - src, 0.5), 6) AS r, CAST(dst % 7 AS BIGINT) AS m FROM e"))
def fn_math(spark, sf_dir):
    s, d = F.col("src"), F.col("dst")
    return _g(spark, sf_dir).edges.select("src", "dst", F.round(F.log(d), 6).alias("l"), F.round(F.exp(s / 1000), 6).alias("x"), F.round(F.pow(d - s, F.lit(0.5)), 6).alias("r"), F.pmod(d, F.lit(7)).alias("m"))


@query(sql(COP, select="SELECT md5(src || '-' || dst) AS h, sha256(CAST(src AS VARCHAR)) AS s FROM e"))
def fn_md5(spark, sf_dir):
    return _g(spark, sf_dir).edges.select(F.md5(F.concat_ws("-", F.col("src").cast("string"), F.col("dst").cast("string"))).alias("h"), F.sha2(F.col("src").cast("string"), 256).alias("s"))


@query(sql(SUP, select=f"SELECT lo, count(*) AS n_keys, CAST(sum(n) AS BIGINT) AS total FROM ({_TOP}) GROUP BY 1"))
def fn_map(spark, sf_dir):
    """A pattern map for each label, and what its keys and values say."""
    maps = agg_pattern(spark, sf_dir).groupBy("lo").agg(F.map_from_entries(F.collect_list(F.struct("hi", "n"))).alias("m"))
    return maps.select("lo", F.size(F.map_keys("m")).cast("long").alias("n_keys"), F.aggregate(F.map_values("m"), F.lit(0).cast("long"), lambda s, q: s + q).alias("total"))


@query(sql(COP, select="SELECT CAST(src AS BIGINT) AS a, CAST(dst + 1 AS BIGINT) AS b FROM e"))
def fn_struct(spark, sf_dir):
    s = F.struct(F.col("src").alias("a"), F.col("dst").alias("b"))
    return _g(spark, sf_dir).edges.select(s.withField("b", F.col("dst") + 1).alias("s")).select("s.a", "s.b")


@query("SELECT p_partkey AS id, upper(p_brand) AS u, lower(trim(p_type)) AS l, lpad(CAST(p_size AS VARCHAR), 4, '0') AS padded, substring(p_name, 1, 5) AS head, regexp_extract(p_brand, '([0-9]+)', 1) AS digits FROM part")
def fn_string(spark, sf_dir):
    c = F.col
    return read_table(spark, sf_dir, "part").select(c("p_partkey").alias("id"), F.upper("p_brand").alias("u"), F.lower(F.trim("p_type")).alias("l"), F.lpad(c("p_size").cast("string"), 4, "0").alias("padded"), F.substring("p_name", 1, 5).alias("head"), F.regexp_extract("p_brand", "([0-9]+)", 1).alias("digits"))


@query("SELECT page_id, regexp_extract(url, '^https?://([^/?#]+)', 1) AS host, nullif(regexp_extract(url, '[?&]page=([^&#]*)', 1), '') AS page FROM pages")
def fn_url(spark, sf_dir):
    return read_table(spark, sf_dir, "pages").select("page_id", F.parse_url("url", F.lit("HOST")).alias("host"), F.parse_url("url", F.lit("QUERY"), F.lit("page")).alias("page"))


@query("SELECT event_id, CAST(date_trunc('hour', ts) AS VARCHAR) AS hour, epoch_us(ts) AS us, CAST(datediff('day', DATE '2024-01-01', CAST(ts AS DATE)) AS INTEGER) AS days FROM events")
def fn_date(spark, sf_dir):
    ts = F.col("ts").cast("timestamp")
    return read_table(spark, sf_dir, "events").select("event_id", F.date_format(F.date_trunc("hour", ts), "yyyy-MM-dd HH:mm:ss").alias("hour"), F.unix_micros(ts).alias("us"), F.datediff(F.to_date(ts), F.lit("2024-01-01").cast("date")).alias("days"))


@query("SELECT event_id, CAST(json_extract_string(props, '$.k') AS BIGINT) AS k FROM events")
def fn_json(spark, sf_dir):
    return read_table(spark, sf_dir, "events").select("event_id", F.from_json("props", "k long")["k"].alias("k"))


@query("SELECT event_id, CASE WHEN value > 10 THEN 'high' WHEN value > 5 THEN 'middle' ELSE 'low' END AS level, coalesce(nullif(event_type, 'view'), 'none') AS kind FROM events")
def fn_cond(spark, sf_dir):
    v = F.col("value")
    return read_table(spark, sf_dir, "events").select("event_id", F.when(v > 10, "high").when(v > 5, "middle").otherwise("low").alias("level"), F.coalesce(F.nullif(F.col("event_type"), F.lit("view")), F.lit("none")).alias("kind"))


@query(sql(COP, select="SELECT CAST(src AS BIGINT) AS vert, CAST(0 AS INTEGER) AS place, count(*) AS n FROM e GROUP BY 1 UNION ALL SELECT CAST(dst AS BIGINT), 1, count(*) FROM e GROUP BY 1"))
def table_functions(spark, sf_dir):
    """A level read through a table function: the vertices at each place."""
    from levelmine.functions.sql import register

    register(spark)
    _views(spark, sf_dir)
    return spark.sql("SELECT vert, place, count(*) AS n FROM decode_level(TABLE(SELECT array(src, dst) AS path FROM edges)) GROUP BY vert, place")


@query(sql(COP, select="SELECT src || '-' || dst AS path FROM e"))
def sql_functions(spark, sf_dir):
    """The functions registered for SQL: a level as a table function, a pattern's code and name."""
    from levelmine.functions.sql import register

    register(spark)
    _views(spark, sf_dir)
    out = spark.sql("SELECT path, pattern_name(pattern_code(array(1, 1), 1L)) AS shape FROM (SELECT array(src, dst) AS path FROM edges) WHERE canonical_ok(path, array(0L, 1L))")
    return out.filter("shape = 'edge'").select(_text(name="path", ordered=False))
