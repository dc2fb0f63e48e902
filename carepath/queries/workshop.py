"""Queries for the relational operators around the methods, one key per operator."""

from __future__ import annotations

from pyspark.sql import Window
from pyspark.sql import functions as F

from carepath.functions import sqlfns
from carepath.operators import codes as C
from carepath.operators import cohorts, folds, relational, temporal
from carepath.queries._registry import DX, ENC, HASH, query
from carepath.queries.visits import _SESS, _sessions
from carepath.sources import events as EV
from carepath.sources import retail
from carepath.sources.tables import load, load_as, save_as


def _enc(s, d):
    return retail.encounters(s, d)


@query("r01_scan", "SELECT o_orderkey, o_custkey FROM orders")
def _(s, d):
    return load(s, d, "orders", ["o_orderkey", "o_custkey"])


@query("r02_formats", "SELECT f, n_nationkey, n_name FROM nation, (VALUES ('csv'), ('json'), ('orc')) v(f)")
def _(s, d):
    from carepath.sources.stores import scratch

    out = None
    for fmt in ("csv", "json", "orc"):
        path = f"{scratch(s)}/nation-{fmt}"
        save_as(load(s, d, "nation"), path, fmt)
        part = load_as(s, path, fmt, "n_nationkey INT, n_name STRING, n_regionkey INT").select(F.lit(fmt).alias("f"), "n_nationkey", "n_name")
        out = part if out is None else out.unionByName(part)
    return out


@query("r05_projection", "SELECT l_orderkey, l_linenumber, round(l_extendedprice * (1 - l_discount), 4) AS net FROM lineitem")
def _(s, d):
    return load(s, d, "lineitem").select("l_orderkey", "l_linenumber", F.round(F.col("l_extendedprice") * (1 - F.col("l_discount")), 4).alias("net"))


@query("r06_filter", "SELECT doc_id FROM documents WHERE source IN ('src1', 'src2') AND n_chars BETWEEN 100 AND 5000 AND text LIKE '%the%' AND lang IS NOT NULL")
def _(s, d):
    return load(s, d, "documents").filter(F.col("source").isin("src1", "src2") & F.col("n_chars").between(100, 5000) & F.col("text").like("%the%") & F.col("lang").isNotNull()).select("doc_id")


@query("r07_equi_join", "SELECT o_custkey AS subject_id, count(*) AS codes FROM orders JOIN lineitem ON l_orderkey = o_orderkey GROUP BY o_custkey")
def _(s, d):
    return relational.visit_codes(_enc(s, d), retail.code_events(s, d, "D")).groupBy("subject_id").agg(F.count("*").alias("codes"))


@query("r08_dictionary_join", "SELECT l_orderkey AS visit_id, l_linenumber AS seq, p_brand AS code FROM lineitem JOIN part ON l_partkey = p_partkey")
def _(s, d):
    return C.map_codes(retail.code_events(s, d, "D"), retail.code_dict(s, d, "D"), "grp").select("visit_id", "seq", "code")


@query("r09_left_join_mask", "SELECT o_orderkey AS visit_id, doc_id IS NOT NULL AS has_note FROM orders LEFT JOIN documents ON doc_id = o_orderkey")
def _(s, d):
    return relational.attach_notes(_enc(s, d).select("visit_id"), retail.notes(s, d)).select("visit_id", "has_note")


@query("r10_full_join", "SELECT coalesce(a.doc_id, b.doc_id) AS doc_id, CASE WHEN a.doc_id IS NULL THEN 'right' WHEN b.doc_id IS NULL THEN 'left' ELSE 'both' END AS side FROM (SELECT * FROM labels WHERE quality = 1) a FULL JOIN (SELECT * FROM labels WHERE toxic = 0) b ON a.doc_id = b.doc_id")
def _(s, d):
    x = load(s, d, "labels")
    return relational.reconcile(x.filter("quality = 1"), x.filter("toxic = 0"), "doc_id", "toxic").select("doc_id", "side")


@query("r11_semi_join", "SELECT o_orderkey AS visit_id FROM orders WHERE o_orderkey IN (SELECT doc_id FROM documents)")
def _(s, d):
    return relational.keep_if(_enc(s, d), retail.notes(s, d), "visit_id").select("visit_id")


@query("r12_anti_join", "SELECT o_orderkey AS visit_id FROM orders WHERE o_orderkey NOT IN (SELECT l_orderkey FROM lineitem)")
def _(s, d):
    return relational.drop_if(_enc(s, d), retail.code_events(s, d, "D"), "visit_id").select("visit_id")


@query("r14_asof_join", "SELECT o_orderkey, coalesce((SELECT max(e.event_id) FROM events e WHERE e.user_id = o_custkey AND e.ts = (SELECT max(f.ts) FROM events f WHERE f.user_id = o_custkey AND f.ts <= o_orderdate)), -1) AS event_id FROM orders")
def _(s, d):
    left = load(s, d, "orders").select("o_orderkey", F.col("o_custkey").alias("who"), F.col("o_orderdate").alias("at"))
    right = load(s, d, "events").groupBy(F.col("user_id").alias("who"), F.col("ts").alias("at")).agg(F.max("event_id").alias("event_id"))
    return relational.asof(left, right, "at", "who", "event_id").select("o_orderkey", F.coalesce("event_id", F.lit(-1)).alias("event_id"))


@query("r15_interval_join", _SESS + " SELECT event_id, visit_id FROM events JOIN ses ON user_id = subject_id AND ts >= admit_ts AND ts <= discharge_ts")
def _(s, d):
    e = load(s, d, "events").select("event_id", "ts", F.col("user_id").alias("subject_id"))
    spans = _sessions(s, d).select("subject_id", "visit_id", "admit_ts", "discharge_ts")
    return relational.in_interval(e, spans, "ts", "admit_ts", "discharge_ts", "subject_id").select("event_id", "visit_id")


@query("r16_grid", "SELECT t, c FROM (SELECT DISTINCT l_discount AS t FROM lineitem), (SELECT DISTINCT o_orderpriority AS c FROM orders)")
def _(s, d):
    thresholds = load(s, d, "lineitem", ["l_discount"]).select(F.col("l_discount").alias("t")).distinct()
    return relational.grid(thresholds, load(s, d, "orders", ["o_orderpriority"]).select(F.col("o_orderpriority").alias("c")).distinct())


@query("r17_aggregate_having", "SELECT o_custkey AS subject_id, count(*) AS visits FROM orders GROUP BY o_custkey HAVING count(*) > 12")
def _(s, d):
    return _enc(s, d).groupBy("subject_id").agg(F.count("*").alias("visits")).filter("visits > 12")


@query("r18_distinct", "SELECT count(DISTINCT l_partkey) AS parts, count(DISTINCT l_suppkey) AS suppliers FROM lineitem")
def _(s, d):
    return load(s, d, "lineitem").agg(F.countDistinct("l_partkey").alias("parts"), F.countDistinct("l_suppkey").alias("suppliers"))


@query("r18_approx_distinct", "SELECT unnest(['raw', 'parent', 'group', 'concept']) AS stage, true AS within")
def _(s, d):
    """Sketched counts against exact ones: within three times the sketch's stated deviation."""
    events, dictionary = retail.code_events(s, d, "D"), retail.code_dict(s, d, "D")
    exact = C.vocab_report(events, dictionary).withColumnRenamed("size", "exact")
    return C.vocab_report(events, dictionary, approx=True).join(exact, "stage").select("stage", (F.abs(F.col("size") - F.col("exact")) <= 0.06 * F.col("exact") + 1).alias("within"))


@query("r19_percentiles", "SELECT quantile_cont(v, 0.25) AS q1, quantile_cont(v, 0.5) AS q2, quantile_cont(v, 0.9) AS q9 FROM (SELECT CAST(count(*) AS DOUBLE) AS v FROM orders GROUP BY o_custkey)")
def _(s, d):
    per = _enc(s, d).groupBy("subject_id").agg(F.count("*").alias("v"))
    return per.agg(*(F.percentile("v", F.lit(p)).alias(n) for p, n in ((0.25, "q1"), (0.5, "q2"), (0.9, "q9"))))


@query("r20_conditional", ENC + " SELECT count(*) FILTER (y = 1) AS returns, max_by(visit_id, (discharge - admit) * 1000000 + visit_id) AS longest, CAST(count(*) FILTER (urgency = '1-URGENT' AND y = 1) AS BIGINT) AS urgent FROM lab")
def _(s, d):
    rows = temporal.stay_length(temporal.return_label(_enc(s, d)))
    return rows.agg(F.count_if(F.col("y_return") == 1).alias("returns"), F.max_by("visit_id", F.col("stay_days") * 1000000 + F.col("visit_id")).alias("longest"), F.count_if((F.col("urgency") == "1-URGENT") & (F.col("y_return") == 1)).alias("urgent"))


def _sets(name, how):
    @query(name, f"SELECT coalesce(o_orderpriority, 'all') AS p, coalesce(o_orderstatus, 'all') AS st, count(*) AS n FROM orders GROUP BY {how.upper()} (o_orderpriority, o_orderstatus)")
    def _(s, d):
        rows = load(s, d, "orders")
        g = (rows.rollup if how == "rollup" else rows.cube)("o_orderpriority", "o_orderstatus")
        return g.agg(F.count("*").alias("n")).select(F.coalesce("o_orderpriority", F.lit("all")).alias("p"), F.coalesce("o_orderstatus", F.lit("all")).alias("st"), "n")


_sets("r21_rollup", "rollup")
_sets("r21_cube", "cube")


@query("r21_grouping_sets", "SELECT coalesce(o_orderpriority, 'all') AS p, coalesce(o_orderstatus, 'all') AS st, count(*) AS n FROM orders GROUP BY GROUPING SETS ((o_orderpriority), (o_orderstatus))")
def _(s, d):
    return s.sql("SELECT coalesce(o_orderpriority, 'all') AS p, coalesce(o_orderstatus, 'all') AS st, count(*) AS n FROM {o} GROUP BY GROUPING SETS ((o_orderpriority), (o_orderstatus))", o=load(s, d, "orders"))


@query("r22_pivot", "SELECT o_orderpriority AS p, CAST(count(*) FILTER (o_orderstatus = 'F') AS BIGINT) AS f, CAST(count(*) FILTER (o_orderstatus = 'O') AS BIGINT) AS o FROM orders GROUP BY 1")
def _(s, d):
    t = load(s, d, "orders").groupBy(F.col("o_orderpriority").alias("p")).pivot("o_orderstatus", ["F", "O"]).count()
    return t.select("p", F.coalesce("F", F.lit(0)).alias("f"), F.coalesce("O", F.lit(0)).alias("o"))


@query("r22_unpivot", "SELECT doc_id, k, v FROM (SELECT doc_id, unnest(['quality', 'toxic']) AS k, unnest([quality, toxic]) AS v FROM labels)")
def _(s, d):
    return load(s, d, "labels").unpivot("doc_id", ["quality", "toxic"], "k", "v").withColumn("v", F.col("v").cast("int"))


@query("r23_collect", "SELECT l_orderkey, string_agg(DISTINCT l_returnflag, ',' ORDER BY l_returnflag) AS flags FROM lineitem GROUP BY l_orderkey")
def _(s, d):
    return load(s, d, "lineitem").groupBy("l_orderkey").agg(F.array_join(F.array_sort(F.collect_set("l_returnflag")), ",").alias("flags"))


@query("r24_ranking", "SELECT c_custkey, row_number() OVER w AS rn, rank() OVER v AS rk, dense_rank() OVER v AS dr, ntile(10) OVER w AS decile, round(percent_rank() OVER v, 6) AS pr, round(cume_dist() OVER v, 6) AS cd FROM customer WINDOW w AS (PARTITION BY c_nationkey ORDER BY c_acctbal DESC, c_custkey), v AS (PARTITION BY c_nationkey ORDER BY c_acctbal DESC, c_custkey)")
def _(s, d):
    r = relational.rank_by(load(s, d, "customer"), ["c_nationkey"], [F.desc("c_acctbal"), "c_custkey"])
    big = lambda c, n: F.col(c).cast("bigint").alias(n)
    return r.select("c_custkey", big("row_number", "rn"), big("rank", "rk"), big("dense_rank", "dr"), big("decile", "decile"), F.round("percent_rank", 6).alias("pr"), F.round("cume_dist", 6).alias("cd"))


@query("r25_analytic", "SELECT o_orderkey, lag(o_orderkey) OVER w AS a, lead(o_orderkey) OVER w AS b, first_value(o_orderkey) OVER w AS c, nth_value(o_orderkey, 2) OVER (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING) AS e FROM orders WINDOW w AS (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey)")
def _(s, d):
    w = Window.partitionBy("o_custkey").orderBy("o_orderdate", "o_orderkey")
    k, whole = "o_orderkey", w.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    return load(s, d, "orders").select(k, F.lag(k).over(w).alias("a"), F.lead(k).over(w).alias("b"), F.first(k).over(w).alias("c"), F.nth_value(k, 2).over(whole).alias("e"))


@query("r26_rows_frame", "SELECT o_orderkey, round(sum(o_totalprice) OVER (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey ROWS BETWEEN 2 PRECEDING AND CURRENT ROW), 2) AS s FROM orders")
def _(s, d):
    w = Window.partitionBy("o_custkey").orderBy("o_orderdate", "o_orderkey").rowsBetween(-2, 0)
    return load(s, d, "orders").select("o_orderkey", F.round(F.sum("o_totalprice").over(w), 2).alias("s"))


@query("r27_range_frame", "SELECT o_orderkey AS visit_id, count(*) OVER (PARTITION BY o_custkey ORDER BY CAST(o_orderdate AS DATE) RANGE BETWEEN INTERVAL 365 DAY PRECEDING AND CURRENT ROW) AS visits_365d FROM orders")
def _(s, d):
    return temporal.lookback_count(_enc(s, d), 365).select("visit_id", "visits_365d")


@query("r28_running_sum", "SELECT o_orderkey, count(*) OVER (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey) AS n FROM orders")
def _(s, d):
    w = Window.partitionBy("o_custkey").orderBy("o_orderdate", "o_orderkey").rowsBetween(Window.unboundedPreceding, 0)
    return load(s, d, "orders").select("o_orderkey", F.count("*").over(w).alias("n"))


@query("r29_sort_limit", "SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 20 OFFSET 10")
def _(s, d):
    return load(s, d, "orders", ["o_orderkey", "o_totalprice"]).orderBy(F.desc("o_totalprice"), "o_orderkey").offset(10).limit(20)


@query("r30_top_k", "SELECT l_partkey, n FROM (SELECT l_partkey, count(*) AS n FROM lineitem GROUP BY 1) ORDER BY n DESC, l_partkey LIMIT 10")
def _(s, d):
    return relational.top_k(load(s, d, "lineitem", ["l_partkey"]).groupBy("l_partkey").agg(F.count("*").alias("n")), [F.desc("n"), "l_partkey"], 10)


@query("r30_top_k_per", "SELECT o_custkey, o_orderkey FROM (SELECT *, row_number() OVER (PARTITION BY o_custkey ORDER BY o_totalprice DESC, o_orderkey) AS r FROM orders) WHERE r <= 2")
def _(s, d):
    return relational.top_k(load(s, d, "orders"), [F.desc("o_totalprice"), "o_orderkey"], 2, ["o_custkey"]).select("o_custkey", "o_orderkey")


@query("r31_union", "SELECT c_nationkey AS k FROM customer UNION SELECT s_nationkey FROM supplier")
def _(s, d):
    return load(s, d, "customer").select(F.col("c_nationkey").alias("k")).union(load(s, d, "supplier").select(F.col("s_nationkey").alias("k"))).distinct()


@query("r32_intersect", "SELECT o_custkey AS k FROM orders INTERSECT SELECT user_id FROM events")
def _(s, d):
    return load(s, d, "orders").select(F.col("o_custkey").alias("k")).intersect(load(s, d, "events").select(F.col("user_id").alias("k")))


@query("r33_except", "SELECT doc_id AS k FROM documents EXCEPT SELECT doc_id FROM labels")
def _(s, d):
    return load(s, d, "documents").select(F.col("doc_id").alias("k")).exceptAll(load(s, d, "labels").select(F.col("doc_id").alias("k")))


@query("r34_subquery", "SELECT c_custkey FROM customer c WHERE EXISTS (SELECT 1 FROM orders o WHERE o.o_custkey = c.c_custkey AND o.o_totalprice > (SELECT avg(o_totalprice) * 1.8 FROM orders))")
def _(s, d):
    return s.sql("SELECT c_custkey FROM {c} c WHERE EXISTS (SELECT 1 FROM {o} o WHERE o.o_custkey = c.c_custkey AND o.o_totalprice > (SELECT avg(o_totalprice) * 1.8 FROM {o}))", c=load(s, d, "customer"), o=load(s, d, "orders"))


@query("r35_cte_params", "WITH v AS (SELECT o_custkey, count(*) AS n FROM orders GROUP BY 1) SELECT o_custkey, n FROM v WHERE n >= 12")
def _(s, d):
    sqlfns.register_views(s, d)
    return s.sql("WITH v AS (SELECT o_custkey, count(*) AS n FROM orders GROUP BY 1) SELECT o_custkey, n FROM v WHERE n >= :least", args={"least": 12})


@query("r36_strings", "SELECT p_partkey, lower(trim(p_name)) || '/' || substr(p_type, 1, 3) || '/' || lpad(CAST(p_size AS VARCHAR), 3, '0') AS k, regexp_extract(p_brand, '([0-9]+)', 1) AS digits, levenshtein(p_name, p_type) AS distance, md5(p_name) AS h FROM part")
def _(s, d):
    k = F.concat_ws("/", F.lower(F.trim("p_name")), F.substring("p_type", 1, 3), F.lpad(F.col("p_size").cast("string"), 3, "0"))
    return load(s, d, "part").select("p_partkey", k.alias("k"), F.regexp_extract("p_brand", "([0-9]+)", 1).alias("digits"), F.levenshtein("p_name", "p_type").cast("bigint").alias("distance"), F.md5("p_name").alias("h"))


@query("r37_dates", "SELECT o_orderkey, CAST(year(o_orderdate) AS INTEGER) AS y, CAST(quarter(o_orderdate) AS INTEGER) AS q, CAST(CAST(date_trunc('month', o_orderdate) AS DATE) AS VARCHAR) AS m, CAST(CAST(o_orderdate AS DATE) + 30 AS VARCHAR) AS due FROM orders")
def _(s, d):
    day = F.to_date("o_orderdate")
    return load(s, d, "orders").select("o_orderkey", F.year(day).alias("y"), F.quarter(day).alias("q"), F.trunc(day, "month").cast("string").alias("m"), F.date_add(day, 30).cast("string").alias("due"))


@query("r38_math", "SELECT l_orderkey, l_linenumber, l_partkey, l_suppkey, round(ln(l_quantity) + sqrt(l_tax) + exp(-l_discount) + greatest(l_tax, l_discount), 6) AS x, CAST(ceil(l_quantity / 7) AS BIGINT) AS c FROM lineitem")
def _(s, d):
    x = F.ln("l_quantity") + F.sqrt("l_tax") + F.exp(-F.col("l_discount")) + F.greatest("l_tax", "l_discount")
    return load(s, d, "lineitem").select("l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", F.round(x, 6).alias("x"), F.ceil(F.col("l_quantity") / 7).alias("c"))


@query("r39_arrays", "WITH w AS (SELECT doc_id, string_split(text, ' ') AS a FROM documents) SELECT doc_id, CAST(len(a) AS BIGINT) AS n, CAST(len(list_distinct(a)) AS BIGINT) AS u, array_to_string(list_reverse(a[1:3]), ' ') AS r FROM w")
def _(s, d):
    a = F.split("text", " ", -1)
    return load(s, d, "documents").select("doc_id", F.size(a).cast("bigint").alias("n"), F.size(F.array_distinct(a)).cast("bigint").alias("u"), F.array_join(F.reverse(F.slice(a, 1, 3)), " ").alias("r"))


@query("r40_maps", "WITH x AS (SELECT l_orderkey, l_returnflag FROM lineitem) SELECT l_orderkey, string_agg(CASE l_returnflag WHEN 'A' THEN 'x' WHEN 'N' THEN 'y' END, '' ORDER BY l_returnflag) AS m FROM x WHERE l_returnflag IN ('A', 'N') GROUP BY l_orderkey")
def _(s, d):
    rows = load(s, d, "lineitem").groupBy("l_orderkey").agg(F.array_sort(F.collect_list("l_returnflag")).alias("f"))
    return rows.select("l_orderkey", F.array_join(C.map_in_row(F.col("f"), {"A": "x", "N": "y"}), "").alias("m")).filter("m <> ''")


@query("r41_json", "SELECT event_type, json_extract_string(props, '$.k') AS k, count(*) AS n FROM events GROUP BY 1, 2")
def _(s, d):
    return EV.details(load(s, d, "events")).groupBy("event_type", "k").agg(F.count("*").alias("n"))


@query("r45_sample", f"SELECT c_custkey FROM customer WHERE {HASH.format(key='c_custkey', seed=7)} / 4294967296.0::DOUBLE < 0.2::DOUBLE")
def _(s, d):
    return load(s, d, "customer").filter(folds.uniform("c_custkey", seed=7) < 0.2).select("c_custkey")


@query("r46_nulls", "SELECT doc_id, coalesce(toxic, -1) AS toxic, quality IS NULL AS missing FROM documents LEFT JOIN labels USING (doc_id)")
def _(s, d):
    rows = load(s, d, "documents", ["doc_id"]).join(load(s, d, "labels"), "doc_id", "left")
    return rows.withColumn("missing", F.col("quality").isNull()).na.fill({"toxic": -1}).select("doc_id", "toxic", "missing")


@query("r47_dedupe", "SELECT l_orderkey, l_linenumber, min(l_partkey) AS l_partkey FROM lineitem GROUP BY 1, 2")
def _(s, d):
    return relational.dedupe(load(s, d, "lineitem"), ["l_orderkey", "l_linenumber"], ["l_partkey", "l_suppkey", "l_shipdate"]).select("l_orderkey", "l_linenumber", "l_partkey")


@query("u_sql_functions", "SELECT p_partkey, 'D_' || substr(upper(p_type), 1, CASE WHEN starts_with(upper(p_type), 'E') THEN 4 ELSE 3 END) AS dx, round((0.9 + 0.5 * (p_size % 5) / 2.0) / (1 + (p_size % 5) / 2.0), 6) AS p FROM part")
def _(s, d):
    sqlfns.register(s)
    load(s, d, "part").createOrReplaceTempView("part")
    return s.sql("SELECT p_partkey, condense_dx(p_type) AS dx, round(merge_chunks_p(0.9D, 0.5D, CAST(p_size % 5 AS BIGINT)), 6) AS p FROM part")


@query("u_chunk_text", "WITH w AS (SELECT doc_id AS note_id, list_filter(string_split(coalesce(text, ''), ' '), lambda x: x <> '') AS words FROM documents), c AS (SELECT note_id, words, unnest(range(0, CAST(ceil(len(words) / 512.0) AS BIGINT))) AS i FROM w) SELECT note_id, CAST(i AS INTEGER) AS chunk_no, CAST(len(words[i * 512 + 1:i * 512 + 512]) AS INTEGER) AS n_tokens FROM c")
def _(s, d):
    return sqlfns.exploded_chunks(retail.notes(s, d).select("note_id", "text"), 512).select("note_id", "chunk_no", "n_tokens")


@query("u_persistence", ENC + DX.format(level="p_brand") + " SELECT q.visit_id, CAST(len(list_intersect(coalesce(a.codes, []), b.codes)) AS BIGINT) AS kept, CAST(len(b.codes) AS BIGINT) AS n_next FROM seq q LEFT JOIN dx a ON a.visit_id = q.visit_id JOIN dx b ON b.visit_id = q.next_visit")
def _(s, d):
    lists = C.ordered_list(C.map_codes(retail.code_events(s, d, "D"), retail.code_dict(s, d, "D"), "grp"), distinct=True)
    return cohorts.carried_over(cohorts.next_dx_dataset(_enc(s, d), lists)).select("visit_id", F.col("kept").cast("bigint").alias("kept"), F.col("n_next").cast("bigint").alias("n_next"))
