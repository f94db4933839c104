"""Scans, joins, aggregates, windows and functions that a user needs around the methods, each over policies or the given tables."""

from __future__ import annotations

from pyspark.sql import functions as F
from pyspark.sql.window import Window

from aclvec.functions.portable import draw, draw_sql
from aclvec.functions.register import register
from aclvec.operators import policy as pol
from aclvec.plans.catalog_parts import mod4, n1, parts
from aclvec.plans.policies_sql import MEASURED, PARTS, POLICIES, SETS, with_
from aclvec.plans.registry import big, query, r6
from aclvec.sources.tables import bucketed, read, vectors

P = with_(POLICIES["n1"])


@query("scan_documents", "SELECT doc_id, lang FROM documents WHERE n_chars > 2000 AND lang = 'en'")
def scan_documents(spark, sf_dir):
    return read(spark, sf_dir, "documents").filter("n_chars > 2000 and lang = 'en'").select("doc_id", "lang")


@query("scan_embeddings", "SELECT vec_id, label FROM embeddings WHERE label IN (1, 3)")
def scan_embeddings(spark, sf_dir):
    return read(spark, sf_dir, "embeddings").filter(F.col("label").isin(1, 3)).select("vec_id", "label")


@query("filter_lang_len", with_(POLICIES["n3"]) + "SELECT doc_id, CASE WHEN n_chars < 1000 THEN 'short' WHEN n_chars BETWEEN 1000 AND 3000 THEN 'medium' ELSE 'long' END AS size FROM documents d WHERE lang IN ('de', 'fr') AND EXISTS (SELECT 1 FROM ua JOIN pa USING (role_id) WHERE user_id = 8 AND pa.doc_id = d.doc_id)")
def filter_lang_len(spark, sf_dir):
    from aclvec.operators.generators import natural_n3

    d = read(spark, sf_dir, "documents").filter(F.col("lang").isin("de", "fr"))
    size = F.when(F.col("n_chars") < 1000, "short").when(F.col("n_chars").between(1000, 3000), "medium").otherwise("long")
    return pol.secure(d, natural_n3(spark, sf_dir), 8).select("doc_id", size.alias("size"))


@query("filter_like", "SELECT p_partkey, p_name FROM part WHERE p_name LIKE '%a%' AND regexp_matches(p_name, '^(red|hot|large) .*[e-t]$')")
def filter_like(spark, sf_dir):
    return read(spark, sf_dir, "part").filter(F.col("p_name").like("%a%") & F.col("p_name").rlike("^(red|hot|large) .*[e-t]$")).select("p_partkey", "p_name")


@query("null_safe_eq", "SELECT count(*) FILTER (WHERE quality IS NOT DISTINCT FROM toxic) AS same FROM documents LEFT JOIN labels USING (doc_id)")
def null_safe_eq(spark, sf_dir):
    d = read(spark, sf_dir, "documents").select("doc_id").join(read(spark, sf_dir, "labels"), "doc_id", "left")
    return d.agg(F.count(F.when(F.col("quality").eqNullSafe(F.col("toxic")), 1)).alias("same"))


for _name, _hint in (("broadcast", "broadcast"), ("sortmerge", "merge"), ("shuffle_hash", "shuffle_hash")):
    @query(f"join_{_name}", P + "SELECT user_id, count(*) AS n, sum(label)::BIGINT AS labels FROM ua JOIN pa USING (role_id) JOIN embeddings ON vec_id = doc_id GROUP BY user_id")
    def _join(spark, sf_dir, hint=_hint):
        p = n1(spark, sf_dir)
        e = read(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("doc_id"), "label")
        # What a role's documents add to a user is summed once a role, so users never meet documents.
        roles = p.pa.join(e.hint(hint), "doc_id").groupBy("role_id").agg(F.count("*").alias("n"), F.sum("label").alias("labels"))
        return p.ua.join(roles.hint(hint), "role_id").groupBy("user_id").agg(F.sum("n").alias("n"), F.sum("labels").alias("labels"))


@query("join_left", "SELECT d.doc_id, coalesce(quality, -1) AS quality FROM documents d LEFT JOIN labels USING (doc_id)")
def join_left(spark, sf_dir):
    return read(spark, sf_dir, "documents").select("doc_id").join(read(spark, sf_dir, "labels").select("doc_id", "quality"), "doc_id", "left").select("doc_id", F.coalesce("quality", F.lit(-1)).alias("quality"))


@query("join_full", "SELECT coalesce(d.doc_id, l.doc_id) AS doc_id, d.doc_id IS NULL AS only_label FROM (SELECT doc_id FROM documents WHERE doc_id % 2 = 0) d FULL JOIN labels l ON d.doc_id = l.doc_id")
def join_full(spark, sf_dir):
    d = read(spark, sf_dir, "documents").filter("doc_id % 2 = 0").select("doc_id", F.lit(1).alias("here"))
    return d.join(read(spark, sf_dir, "labels").select("doc_id"), "doc_id", "full").select("doc_id", F.col("here").isNull().alias("only_label"))


@query("join_semi", P + "SELECT doc_id FROM docs WHERE doc_id IN (SELECT doc_id FROM pa WHERE role_id = 3)")
def join_semi(spark, sf_dir):
    p = n1(spark, sf_dir)
    return p.docs.join(p.pa.filter("role_id = 3"), "doc_id", "left_semi")


@query("join_anti_orphans", with_(POLICIES["n2"]) + "SELECT doc_id FROM docs WHERE doc_id NOT IN (SELECT doc_id FROM pa)")
def join_anti_orphans(spark, sf_dir):
    from aclvec.operators.generators import natural_n2

    p = natural_n2(spark, sf_dir)
    return p.docs.join(p.pa, "doc_id", "left_anti")


GRANTS = "grants AS (SELECT event_id AS grant_id, user_id, ts AS valid_from, ts + to_seconds((floor(value)::INT % 48) * 3600) AS valid_to FROM events WHERE event_type = 'purchase'), asks AS (SELECT event_id, user_id, ts FROM events WHERE event_type = 'view')"


def _grants(spark, sf_dir):
    e = read(spark, sf_dir, "events")
    hours = F.expr("make_interval(0, 0, 0, 0, cast(value as int) % 48, 0, 0)")
    grants = e.filter("event_type = 'purchase'").select(F.col("event_id").alias("grant_id"), "user_id", F.col("ts").alias("valid_from"), (F.col("ts") + hours).alias("valid_to"))
    return grants, e.filter("event_type = 'view'").select("event_id", "user_id", "ts")


@query("join_grant_interval", with_(GRANTS) + "SELECT event_id, count(grant_id) AS n_grants FROM asks LEFT JOIN grants ON grants.user_id = asks.user_id AND valid_from <= ts AND ts < valid_to GROUP BY event_id")
def join_grant_interval(spark, sf_dir):
    grants, asks = _grants(spark, sf_dir)
    a = asks.alias("a").join(grants.alias("g"), (F.col("a.user_id") == F.col("g.user_id")) & (F.col("valid_from") <= F.col("ts")) & (F.col("ts") < F.col("valid_to")), "left")
    return a.groupBy("event_id").agg(F.count("grant_id").alias("n_grants"))


@query("join_asof_policy", with_(GRANTS) + "SELECT event_id, coalesce((SELECT strftime(max(valid_from), '%Y-%m-%d %H:%M:%S.%f') FROM grants WHERE grants.user_id = asks.user_id AND valid_from <= ts), 'none') AS version FROM asks")
def join_asof_policy(spark, sf_dir):
    """The last grant at or before each view: one window over the union, no join on ranges."""
    grants, asks = _grants(spark, sf_dir)
    both = grants.select("user_id", F.col("valid_from").alias("ts"), F.lit(0).alias("ask"), F.col("valid_from").alias("v"), F.lit(None).cast("long").alias("event_id")).union(asks.select("user_id", "ts", F.lit(1), F.lit(None).cast("timestamp_ntz"), "event_id"))
    last = F.last("v", True).over(Window.partitionBy("user_id").orderBy("ts", "ask").rowsBetween(Window.unboundedPreceding, 0))
    found = both.withColumn("last_v", last).filter("ask = 1")
    return found.select("event_id", F.coalesce(F.date_format("last_v", "yyyy-MM-dd HH:mm:ss.SSSSSS"), F.lit("none")).alias("version"))


@query("agg_role_sizes", P + "SELECT role_id::BIGINT AS role_id, count(*) AS n, min(doc_id) AS lo, max(doc_id) AS hi FROM pa GROUP BY role_id")
def agg_role_sizes(spark, sf_dir):
    return n1(spark, sf_dir).pa.groupBy(big("role_id").alias("role_id")).agg(F.count("*").alias("n"), F.min("doc_id").alias("lo"), F.max("doc_id").alias("hi"))


@query("agg_distinct", P + "SELECT count(DISTINCT role_id) AS roles, count(DISTINCT doc_id) AS docs FROM pa")
def agg_distinct(spark, sf_dir):
    return n1(spark, sf_dir).pa.agg(F.countDistinct("role_id").alias("roles"), F.countDistinct("doc_id").alias("docs"))


for _kind, _sql in (("cube", "CUBE (lang, source)"), ("rollup", "ROLLUP (lang, source)"), ("grouping_sets", "GROUPING SETS ((lang), (source), ())")):
    @query(f"agg_{_kind}", f"SELECT coalesce(lang, '*') AS lang, coalesce(source, '*') AS source, count(*) AS n, sum(n_chars)::BIGINT AS chars FROM documents GROUP BY {_sql}")
    def _agg(spark, sf_dir, kind=_kind):
        d = read(spark, sf_dir, "documents").select("lang", "source", "n_chars")
        if kind == "grouping_sets":
            grouped = d.groupingSets([("lang",), ("source",), ()], "lang", "source")
        else:
            grouped = getattr(d, kind)("lang", "source")
        return grouped.agg(F.count("*").alias("n"), F.sum("n_chars").alias("chars")).select(F.coalesce("lang", F.lit("*")).alias("lang"), F.coalesce("source", F.lit("*")).alias("source"), "n", "chars")


@query("pivot_report", with_(POLICIES["n3"]) + "SELECT source, count(*) FILTER (WHERE lang = 'de') AS de, count(*) FILTER (WHERE lang = 'en') AS en, count(*) FILTER (WHERE lang = 'es') AS es, count(*) FILTER (WHERE lang = 'fr') AS fr FROM documents GROUP BY source")
def pivot_report(spark, sf_dir):
    langs = ["de", "en", "es", "fr"]
    return read(spark, sf_dir, "documents").groupBy("source").pivot("lang", langs).count().select("source", *(F.coalesce(c, F.lit(0)).alias(c) for c in langs))


@query("unpivot_report", "SELECT doc_id, measure, value::BIGINT AS value FROM (SELECT doc_id, quality, toxic FROM labels) UNPIVOT (value FOR measure IN (quality, toxic))")
def unpivot_report(spark, sf_dir):
    return read(spark, sf_dir, "labels").unpivot("doc_id", ["quality", "toxic"], "measure", "value").withColumn("value", big("value"))


@query("theta_union_size")
def theta_union_size(spark, sf_dir):
    """The size of all roles' union by a sketch: for planning where classes would be too many."""
    p = n1(spark, sf_dir)
    return p.pa.agg(F.approx_count_distinct("doc_id", 0.02).alias("estimate"), F.countDistinct("doc_id").alias("exact"))


@query("percentiles", "SELECT event_type, round(quantile_cont(value, 0.5), 6) AS p50, round(quantile_cont(value, 0.95), 6) AS p95, round(stddev_samp(value), 6) AS sd FROM events GROUP BY event_type")
def percentiles(spark, sf_dir):
    e = read(spark, sf_dir, "events").select("event_type", "value")
    return e.groupBy("event_type").agg(r6(F.percentile("value", 0.5)).alias("p50"), r6(F.percentile("value", 0.95)).alias("p95"), r6(F.stddev_samp("value")).alias("sd"))


@query("win_topk", P + "SELECT role_id::BIGINT AS role_id, doc_id, r FROM (SELECT role_id, doc_id, row_number() OVER (PARTITION BY role_id ORDER BY doc_id DESC) AS r FROM pa) WHERE r <= 3")
def win_topk(spark, sf_dir):
    w = Window.partitionBy("role_id").orderBy(F.desc("doc_id"))
    return n1(spark, sf_dir).pa.withColumn("r", F.row_number().over(w).cast("long")).filter("r <= 3").select(big("role_id").alias("role_id"), "doc_id", "r")


@query("win_ntile", P + "SELECT role_id::BIGINT AS role_id, ntile(4) OVER (ORDER BY n, role_id) AS quarter, dense_rank() OVER (ORDER BY n) AS dr, round(percent_rank() OVER (ORDER BY n), 6) AS pr, round(cume_dist() OVER (ORDER BY n), 6) AS cd FROM (SELECT role_id, count(*) AS n FROM pa GROUP BY role_id)")
def win_ntile(spark, sf_dir):
    n = n1(spark, sf_dir).pa.groupBy("role_id").agg(F.count("*").alias("n"))  # one row a role
    by = Window.orderBy("n")
    return n.select(big("role_id").alias("role_id"), F.ntile(4).over(Window.orderBy("n", "role_id")).cast("long").alias("quarter"), F.dense_rank().over(by).cast("long").alias("dr"), r6(F.percent_rank().over(by)).alias("pr"), r6(F.cume_dist().over(by)).alias("cd"))


@query("win_lag_curve", "SELECT user_id, event_id, round(value - lag(value) OVER w, 6) AS step, first_value(event_type) OVER w AS first_type FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)")
def win_lag_curve(spark, sf_dir):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    return read(spark, sf_dir, "events").select("user_id", "event_id", r6(F.col("value") - F.lag("value").over(w)).alias("step"), F.first("event_type").over(w).alias("first_type"))


@query("win_running_memory", with_(POLICIES["n1"], SETS, PARTS["role_part"], MEASURED) + "SELECT part, sum(n_docs) OVER (ORDER BY n_docs DESC, part ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW)::BIGINT AS stored FROM sizes")
def win_running_memory(spark, sf_dir):
    w = Window.orderBy(F.desc("n_docs"), "part").rowsBetween(Window.unboundedPreceding, 0)
    return parts(n1(spark, sf_dir), "role_part").sizes().select("part", F.sum("n_docs").over(w).alias("stored"))


@query("win_range_frame", "SELECT user_id, h, count(*) OVER (PARTITION BY user_id ORDER BY h RANGE BETWEEN 5 PRECEDING AND CURRENT ROW) AS recent FROM (SELECT user_id, floor(epoch(ts) / 3600)::BIGINT AS h FROM events)")
def win_range_frame(spark, sf_dir):
    e = read(spark, sf_dir, "events").select("user_id", F.floor(F.unix_timestamp(F.col("ts").cast("timestamp")) / 3600).alias("h"))
    return e.select("user_id", "h", F.count("*").over(Window.partitionBy("user_id").orderBy("h").rangeBetween(-5, 0)).alias("recent"))


@query("sort_topk_shared", P + "SELECT doc_id, count(*) AS degree FROM pa GROUP BY doc_id ORDER BY degree DESC, doc_id LIMIT 10")
def sort_topk_shared(spark, sf_dir):
    return n1(spark, sf_dir).pa.groupBy("doc_id").agg(F.count("*").alias("degree")).orderBy(F.desc("degree"), "doc_id").limit(10)


@query("sort_offset", P + "SELECT doc_id, count(*) AS degree FROM pa GROUP BY doc_id ORDER BY degree DESC, doc_id LIMIT 10 OFFSET 5")
def sort_offset(spark, sf_dir):
    return n1(spark, sf_dir).pa.groupBy("doc_id").agg(F.count("*").alias("degree")).orderBy(F.desc("degree"), "doc_id").offset(5).limit(10)


for _name, _op in (("intersect_roles", "INTERSECT"), ("except_diff", "EXCEPT"), ("union_auth", "UNION")):
    @query(f"set_{_name}", P + f"SELECT doc_id FROM pa WHERE role_id = 100 {_op} SELECT doc_id FROM pa WHERE role_id IN (3, 7)")
    def _set(spark, sf_dir, op=_op):
        pa = n1(spark, sf_dir).pa
        a, b = pa.filter("role_id = 100").select("doc_id"), pa.filter("role_id in (3, 7)").select("doc_id")
        return {"INTERSECT": a.intersect, "EXCEPT": a.subtract, "UNION": lambda x: a.union(x).distinct()}[op](b)


@query("subq_scalar", "SELECT doc_id, n_chars FROM documents d WHERE n_chars > (SELECT 2 * avg(n_chars) FROM documents x WHERE x.lang = d.lang)")
def subq_scalar(spark, sf_dir):
    read(spark, sf_dir, "documents").createOrReplaceTempView("aclvec_documents")
    return spark.sql("SELECT doc_id, n_chars FROM aclvec_documents d WHERE n_chars > (SELECT 2 * avg(n_chars) FROM aclvec_documents x WHERE x.lang = d.lang)")


@query("subq_exists", P + "SELECT user_id FROM users u WHERE EXISTS (SELECT 1 FROM ua WHERE ua.user_id = u.user_id AND role_id >= 100) AND user_id NOT IN (SELECT user_id FROM ua WHERE role_id = 3)")
def subq_exists(spark, sf_dir):
    p = n1(spark, sf_dir)
    return p.users.join(p.ua.filter("role_id >= 100"), "user_id", "left_semi").join(p.ua.filter("role_id = 3"), "user_id", "left_anti")


@query("subq_lateral", P + "SELECT r.role_id::BIGINT AS role_id, x.doc_id FROM (SELECT DISTINCT role_id FROM pa) r, LATERAL (SELECT doc_id FROM pa WHERE pa.role_id = r.role_id ORDER BY doc_id LIMIT 2) x")
def subq_lateral(spark, sf_dir):
    n1(spark, sf_dir).pa.createOrReplaceTempView("aclvec_pa")
    return spark.sql("SELECT CAST(r.role_id AS BIGINT) AS role_id, x.doc_id FROM (SELECT DISTINCT role_id FROM aclvec_pa) r, LATERAL (SELECT doc_id FROM aclvec_pa p WHERE p.role_id = r.role_id ORDER BY doc_id LIMIT 2) x")


@query("sample_hash", f"SELECT doc_id FROM documents WHERE {draw_sql('doc_id', 5, 100)} < 20")
def sample_hash(spark, sf_dir):
    return read(spark, sf_dir, "documents").select("doc_id").filter(draw("doc_id", 5, 100) < 20)


@query("fn_string", "SELECT p_partkey, upper(p_name) AS u, length(trim(p_name)) AS n, substr(p_name, 1, 3) AS head, regexp_replace(p_name, '[0-9]', '#', 'g') AS masked, instr(p_name, 'a') AS at FROM part")
def fn_string(spark, sf_dir):
    return read(spark, sf_dir, "part").select("p_partkey", F.upper("p_name").alias("u"), big(F.length(F.trim("p_name"))).alias("n"), F.substring("p_name", 1, 3).alias("head"), F.regexp_replace("p_name", "[0-9]", "#").alias("masked"), big(F.instr("p_name", "a")).alias("at"))


@query("fn_date", "SELECT o_orderkey, year(o_orderdate) AS y, month(o_orderdate) AS m, date_diff('day', DATE '1992-01-01', o_orderdate::DATE) AS d, strftime(date_trunc('month', o_orderdate), '%Y-%m-%d') AS first FROM orders")
def fn_date(spark, sf_dir):
    d = F.col("o_orderdate")
    return read(spark, sf_dir, "orders").select("o_orderkey", big(F.year(d)).alias("y"), big(F.month(d)).alias("m"), big(F.datediff(d, F.lit("1992-01-01"))).alias("d"), F.date_format(F.date_trunc("month", d), "yyyy-MM-dd").alias("first"))


@query("fn_math", "SELECT p_partkey, round(ln(p_retailprice), 6) AS l, round(sqrt(p_retailprice), 6) AS s, round(pow(p_size, 1.5), 6) AS p, greatest(p_size, 10) AS g, p_size % 7 AS m, round(log2(p_size + 1), 6) AS l2 FROM part")
def fn_math(spark, sf_dir):
    return read(spark, sf_dir, "part").select("p_partkey", r6(F.ln("p_retailprice")).alias("l"), r6(F.sqrt("p_retailprice")).alias("s"), r6(F.pow("p_size", F.lit(1.5))).alias("p"), F.greatest("p_size", F.lit(10)).alias("g"), (F.col("p_size") % 7).alias("m"), r6(F.log2(F.col("p_size") + 1)).alias("l2"))


@query("fn_array_roles", P + "SELECT doc_id, len(a)::BIGINT AS n, list_contains(a, 3) AS has3, array_to_string(list_sort(list_intersect(a, [0, 3, 7, 100])), ',') AS some, list_sum(list_transform(a, lambda x: x * 2))::BIGINT AS doubled FROM (SELECT doc_id, list_sort(list(role_id)) AS a FROM pa GROUP BY doc_id)")
def fn_array_roles(spark, sf_dir):
    a = n1(spark, sf_dir).pa.groupBy("doc_id").agg(F.array_sort(F.collect_list("role_id")).alias("a"))
    some = F.array_sort(F.array_intersect("a", F.array(*(F.lit(x) for x in (0, 3, 7, 100)))))
    return a.select("doc_id", big(F.size("a")).alias("n"), F.array_contains("a", 3).alias("has3"), pol.key_of(some).alias("some"), F.aggregate(F.transform("a", lambda x: x * 2), F.lit(0).cast("long"), lambda s, x: s + x).alias("doubled"))


@query("fn_map_metrics", P + "SELECT doc_id, count(*) FILTER (WHERE role_id < 25) AS nations, count(*) FILTER (WHERE role_id >= 100) AS segments FROM pa GROUP BY doc_id")
def fn_map_metrics(spark, sf_dir):
    kinds = n1(spark, sf_dir).pa.groupBy("doc_id", F.when(F.col("role_id") < 25, "nation").otherwise("segment").alias("kind")).agg(F.count("*").alias("n"))
    m = kinds.groupBy("doc_id").agg(F.map_from_entries(F.collect_list(F.struct("kind", "n"))).alias("m"))
    return m.select("doc_id", F.coalesce(F.element_at("m", F.lit("nation")), F.lit(0)).alias("nations"), F.coalesce(F.element_at("m", F.lit("segment")), F.lit(0)).alias("segments"))


@query("fn_json_props", "SELECT event_type, sum((props->>'k')::BIGINT)::BIGINT AS total, count(*) FILTER (WHERE (props->>'k')::INT > 50) AS big FROM events GROUP BY event_type")
def fn_json_props(spark, sf_dir):
    e = read(spark, sf_dir, "events").select("event_type", F.from_json("props", "k bigint").k.alias("k"))
    return e.groupBy("event_type").agg(F.sum("k").alias("total"), F.count(F.when(F.col("k") > 50, 1)).alias("big"))


@query("fn_bitmask_roles", P + "SELECT doc_id, bit_count(m)::BIGINT AS n, m & 255 AS low FROM (SELECT doc_id, bit_or(1::BIGINT << role_id) AS m FROM pa WHERE role_id < 25 GROUP BY doc_id)")
def fn_bitmask_roles(spark, sf_dir):
    m = n1(spark, sf_dir).pa.filter("role_id < 25").groupBy("doc_id").agg(F.bit_or(F.expr("shiftleft(1L, role_id)")).alias("m"))
    return m.select("doc_id", big(F.bit_count("m")).alias("n"), F.col("m").bitwiseAND(255).alias("low"))


@query("bitmap_auth_size", P + "SELECT role_id::BIGINT AS role_id, count(DISTINCT doc_id) AS n FROM pa GROUP BY role_id")
def bitmap_auth_size(spark, sf_dir):
    pa = n1(spark, sf_dir).pa
    parts_ = pa.groupBy("role_id", F.bitmap_bucket_number("doc_id").alias("b")).agg(F.bitmap_construct_agg(F.bitmap_bit_position("doc_id")).alias("bits"))
    return parts_.groupBy(big("role_id").alias("role_id")).agg(F.sum(F.bitmap_count("bits")).alias("n"))


@query("fn_url_host", r"SELECT page_id, regexp_extract(url, '://([^/?#]*)', 1) AS host, length(regexp_replace(html, '<[^>]*>', '', 'g')) AS plain FROM pages")
def fn_url_host(spark, sf_dir):
    return read(spark, sf_dir, "pages").select("page_id", F.regexp_extract("url", "://([^/?#]*)", 1).alias("host"), big(F.length(F.regexp_replace("html", "<[^>]*>", ""))).alias("plain"))


@query("policy_json_roundtrip", P + "SELECT role_id::BIGINT AS role_id, count(*) AS n, sum(doc_id)::BIGINT AS s FROM pa GROUP BY role_id")
def policy_json_roundtrip(spark, sf_dir):
    """Edges to JSON rows and back."""
    rows = n1(spark, sf_dir).pa.select(F.to_json(F.struct("role_id", "doc_id")).alias("j"))
    back = rows.select(F.from_json("j", "role_id int, doc_id bigint").alias("x")).select("x.*")
    return back.groupBy(big("role_id").alias("role_id")).agg(F.count("*").alias("n"), F.sum("doc_id").alias("s"))


@query("sql_functions", "SELECT 40.0::DOUBLE AS ef, round(ln(1000) * 60, 6) AS cost, round(1 / (1 + exp(-4.0 * (40 * 0.3 / 10 - 0.5))), 6) AS recall, round(10 / 0.3 * (0.5 + ln(0.95 / 0.05) / 4), 6) AS depth")
def sql_functions(spark, sf_dir):
    register(spark)
    return spark.sql("SELECT 40D AS ef, round(acl_cost(1000, 40, 1, 20), 6) AS cost, round(acl_recall(40, 0.3D, 10, 4, 0.5D), 6) AS recall, round(acl_ef(0.95D, 0.3D, 10, 4, 0.5D), 6) AS depth")


@query("udtf_policy")
def udtf_policy(spark, sf_dir):
    register(spark)
    return spark.sql("SELECT role_id, count(*) AS n FROM policy_generate(10, 500, 40) GROUP BY role_id")


@query("source_policy")
def source_policy(spark, sf_dir):
    from aclvec.sources.policy_source import PolicySource

    spark.dataSource.register(PolicySource)
    return spark.read.format("aclvec-policy").option("roles", 10).option("docs", 500).load().groupBy("role_id").agg(F.count("*").alias("n"))


@query("role_home_sizes", with_(POLICIES["n1"]) + "SELECT (role_id % 4)::BIGINT AS partition_id, count(DISTINCT role_id) AS n_roles FROM (SELECT role_id FROM ua UNION SELECT role_id FROM pa) GROUP BY 1")
def role_home_sizes(spark, sf_dir):
    return mod4(n1(spark, sf_dir)).groupBy(big("partition_id").alias("partition_id")).agg(F.count("*").alias("n_roles"))


@query("join_bucketed", P + "SELECT role_id::BIGINT AS role_id, count(*) AS n, sum(label)::BIGINT AS labels FROM pa JOIN embeddings ON vec_id = doc_id GROUP BY role_id")
def join_bucketed(spark, sf_dir):
    """Permission edges and vectors as tables of equal buckets by document: joined where they lie."""
    edges = bucketed(n1(spark, sf_dir).pa, "aclvec_edges", ["doc_id"], 8)
    nodes = bucketed(vectors(spark, sf_dir).select("doc_id", "label"), "aclvec_nodes", ["doc_id"], 8)
    return edges.hint("merge").join(nodes, "doc_id").groupBy(big("role_id").alias("role_id")).agg(F.count("*").alias("n"), big(F.sum("label")).alias("labels"))


@query("sample_by_label")
def sample_by_label(spark, sf_dir):
    """A stratified sample: labels with an even number at a tenth, the others at a half."""
    v = vectors(spark, sf_dir)
    return v.withColumn("odd", F.col("label") % 2).sampleBy("odd", {0: 0.1, 1: 0.5}, seed=5).groupBy("odd").agg(F.count("*").alias("n"))
