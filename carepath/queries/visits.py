"""Queries over visits: times, codes, notes, datasets, folds, sequences, streams in batch form."""

from __future__ import annotations

from pyspark.sql import functions as F

from carepath.functions import scoring, vectors
from carepath.measures import metrics
from carepath.operators import codes as C
from carepath.operators import cohorts, folds, notes, sequences, temporal
from carepath.queries._registry import DX, ENC, HASH, query
from carepath.sources import events as EV
from carepath.sources import retail
from carepath.sources.tables import load
from carepath.streaming import windows as SW

BRAND, PARENT = "p_brand", "p_brand || '|' || p_type"


def _enc(s, d):
    return retail.encounters(s, d)


def _labelled(s, d):
    return temporal.return_label(_enc(s, d))


# ---------------------------------------------------------------- times


@query("t_prior_gap", ENC + " SELECT visit_id, CAST(CASE WHEN prior_discharge IS NULL THEN 0 ELSE greatest(admit - prior_discharge, 0) END AS BIGINT) AS gap_days, prior_discharge IS NOT NULL AS has_prior FROM seq")
def _(s, d):
    return temporal.prior_gap(_enc(s, d)).select("visit_id", F.when(F.col("has_prior"), F.col("gap_days")).otherwise(0).cast("bigint").alias("gap_days"), "has_prior")


@query("t_prior_gap_admit", ENC + " SELECT visit_id, CAST(coalesce(admit - prior_admit, -1) AS BIGINT) AS gap_days FROM seq")
def _(s, d):
    return temporal.prior_gap(_enc(s, d), "admit", first_fill=-1, negative="keep").select("visit_id", F.col("gap_days").cast("bigint").alias("gap_days"))


@query("t_stay", ENC + " SELECT visit_id, CAST(discharge - admit AS BIGINT) AS stay_days FROM enc")
def _(s, d):
    return temporal.stay_length(_enc(s, d)).select("visit_id", F.col("stay_days").cast("bigint").alias("stay_days"))


def _label(name, condition, **options):
    @query(name, ENC + f" SELECT visit_id, CASE WHEN {condition} THEN 1 ELSE 0 END AS y_return FROM seq")
    def _(s, d):
        return temporal.return_label(_enc(s, d), **options).select("visit_id", "y_return")


_label("t_return_fwd", "next_admit - discharge < 30")
_label("t_return_bwd", "admit - prior_discharge < 30", direction="backward")
_label("t_return_urgent", "next_admit - discharge < 30 AND next_urgency IN ('1-URGENT', '2-HIGH')", urgent=retail.urgent)
_label("t_return_inclusive", "next_admit - discharge <= 30", inclusive=True)
_label("t_return_admit", "next_admit - admit < 30", anchor="admit")
_label("r13_range_join", "next_admit - discharge < 30", strategy="range_join")


@query("t_minmax", ENC + ", f AS (SELECT min(discharge - admit) AS a, max(discharge - admit) AS b FROM enc) SELECT visit_id, round((discharge - admit - a) / CAST(b - a AS DOUBLE), 6) AS stay FROM enc, f")
def _(s, d):
    rows = temporal.stay_length(_enc(s, d))
    return temporal.apply_minmax(rows, temporal.fit_minmax(rows, ["stay_days"])).select("visit_id", F.round("stay_days_scaled", 6).alias("stay"))


@query("t_profile", ENC + """, p AS (SELECT subject_id, count(*) AS v, max(y) AS y FROM lab GROUP BY subject_id)
SELECT count(*) AS patients, CAST(sum(y) AS BIGINT) AS positive, CAST(sum(1 - y) AS BIGINT) AS negative, CAST(count(*) FILTER (v = 1) AS BIGINT) AS single_visit,
  CAST(count(*) FILTER (v > 1) AS BIGINT) AS multi_visit, CAST(sum(v) AS BIGINT) AS visits, min(v) AS min_visits, CAST(median(v) AS DOUBLE) AS median_visits, max(v) AS max_visits FROM p""")
def _(s, d):
    return cohorts.profile(_labelled(s, d))


@query("t_patient_label", ENC + " SELECT subject_id, max(y) AS y_patient FROM lab GROUP BY subject_id")
def _(s, d):
    return cohorts.patient_label(_labelled(s, d))


# ---------------------------------------------------------------- codes


def _ordered(name, kind, code, order):
    @query(name, f"SELECT l_orderkey AS visit_id, string_agg({code}, ',' ORDER BY {order}) AS codes, count(*) AS n_codes FROM lineitem GROUP BY l_orderkey")
    def _(s, d):
        return C.ordered_list(retail.code_events(s, d, kind)).select("visit_id", F.array_join("codes", ",").alias("codes"), F.col("n_codes").cast("bigint").alias("n_codes"))


_ordered("c_dx_list", "D", "CAST(l_partkey AS VARCHAR)", "l_linenumber, l_partkey, l_suppkey")
_ordered("c_proc_list", "P", "CAST(l_suppkey AS VARCHAR)", "l_linenumber, l_partkey, l_suppkey")
_ordered("c_med_list", "M", "l_partkey || '-' || l_suppkey", "CAST(l_shipdate AS DATE), l_partkey, l_suppkey")


def _dx(s, d, level="grp", distinct=True):
    mapped = C.map_codes(retail.code_events(s, d, "D"), retail.code_dict(s, d, "D"), level)
    return mapped, C.ordered_list(mapped, distinct=distinct)


@query("c_group_map", "SELECT p_brand AS code, count(*) AS n FROM lineitem JOIN part ON l_partkey = p_partkey GROUP BY p_brand")
def _(s, d):
    return _dx(s, d)[0].groupBy("code").agg(F.count("*").alias("n"))


@query("c_condense", "SELECT 'D_' || substr(upper(p_type), 1, CASE WHEN starts_with(upper(p_type), 'E') THEN 4 ELSE 3 END) AS parent, count(*) AS n FROM part GROUP BY 1")
def _(s, d):
    return load(s, d, "part", ["p_type"]).groupBy(C.condense(F.col("p_type"), "D").alias("parent")).agg(F.count("*").alias("n"))


_SHAPES = "CASE k % 4 WHEN 0 THEN lpad(CAST(k AS {t}), 5, '0') WHEN 1 THEN 'E' || lpad(CAST(k % 10000 AS {t}), 4, '0') WHEN 2 THEN 'v' || lpad(CAST(k % 10000 AS {t}), 4, '0') ELSE CAST(k % 100 AS {t}) END"


@query("c_condense_icd_shapes", f"WITH s AS (SELECT p_partkey AS k FROM part), c AS (SELECT k, {_SHAPES.format(t='VARCHAR')} AS code FROM s) SELECT k, 'D_' || CASE WHEN starts_with(upper(code), 'E') THEN substr(upper(code), 1, 4) ELSE substr(upper(code), 1, 3) END AS dx, 'P_' || substr(upper(code), 1, 2) AS proc FROM c")
def _(s, d):
    codes = load(s, d, "part", ["p_partkey"]).select(F.col("p_partkey").alias("k")).withColumn("code", F.expr(_SHAPES.format(t="STRING")))
    return codes.select("k", C.condense(F.col("code"), "D").alias("dx"), C.condense(F.col("code"), "P").alias("proc"))


@query("c_concept_map", "SELECT p_name AS code, count(*) AS n FROM lineitem JOIN part ON l_partkey = p_partkey GROUP BY p_name")
def _(s, d):
    med = retail.code_events(s, d, "M").withColumn("code", F.substring_index("code", "-", 1))
    return C.map_codes(med, retail.code_dict(s, d, "D"), "concept").groupBy("code").agg(F.count("*").alias("n"))


_VOCAB = "vocab AS (SELECT code, CAST(row_number() OVER (ORDER BY n DESC, code) + 1 AS INTEGER) AS id, n FROM (SELECT {level} AS code, count(*) AS n FROM lineitem JOIN part ON l_partkey = p_partkey GROUP BY 1))"


@query("c_vocab", f"WITH {_VOCAB.format(level=PARENT)} SELECT * FROM vocab")
def _(s, d):
    return C.vocabulary(_dx(s, d, "parent")[0])


@query("c_vocab_report", f"SELECT unnest(['raw', 'parent', 'group', 'concept']) AS stage, unnest([count(DISTINCT l_partkey), count(DISTINCT {PARENT}), count(DISTINCT p_brand), count(DISTINCT p_name)]) AS size FROM lineitem JOIN part ON l_partkey = p_partkey")
def _(s, d):
    return C.vocab_report(retail.code_events(s, d, "D"), retail.code_dict(s, d, "D"))


@query("c_pad", "WITH x AS (SELECT 1)" + DX.format(level=BRAND) + ", z AS (SELECT max(len(codes)) AS n FROM dx) SELECT visit_id, array_to_string(list_concat(codes, list_transform(range(n - len(codes)), lambda i: '')), ',') AS padded, CAST(len(codes) AS BIGINT) AS n_real, n AS size FROM dx, z")
def _(s, d):
    rows = C.pad(_dx(s, d)[1])
    real = F.size(F.filter("mask", lambda m: m)).cast("bigint")
    return rows.select("visit_id", F.array_join("padded", ",").alias("padded"), real.alias("n_real"), F.size("padded").cast("bigint").alias("size"))


@query("c_next_label", ENC + DX.format(level=BRAND) + " SELECT visit_id, next_visit, array_to_string(list_sort(codes), ',') AS label FROM (SELECT seq.visit_id, next_visit, codes FROM seq JOIN dx ON dx.visit_id = next_visit)")
def _(s, d):
    rows = cohorts.next_codes_label(_enc(s, d), _dx(s, d)[1])
    return rows.select("visit_id", "next_visit", F.array_join(F.array_sort("next_codes"), ",").alias("label"))


@query("c_multihot_dense", f"WITH {_VOCAB.format(level=BRAND)}, x AS (SELECT DISTINCT l_orderkey AS visit_id, p_brand AS code FROM lineitem JOIN part ON l_partkey = p_partkey), v AS (SELECT visit_id, list(id) AS ids FROM x JOIN vocab USING (code) GROUP BY visit_id) SELECT visit_id, array_to_string(list_transform(range(2, 27), lambda i: CASE WHEN list_contains(ids, CAST(i AS INTEGER)) THEN 1 ELSE 0 END), '') AS hot FROM v")
def _(s, d):
    mapped, lists = _dx(s, d)
    return C.ids(lists, C.vocabulary(mapped)).select("visit_id", F.array_join(C.multi_hot(F.col("ids"), 25).cast("array<string>"), "").alias("hot"))


@query("c_describe", "SELECT CAST(p_partkey AS VARCHAR) AS code, array_to_string(string_split_regex(lower(p_name || ' ' || p_type || ' ' || p_brand), '\\s+')[1:3], ' ') AS text FROM part")
def _(s, d):
    return C.describe(retail.code_dict(s, d, "D"), 3)


# ---------------------------------------------------------------- notes

_CLEAN = "trim(regexp_replace(regexp_replace({t}, '[^\\p{{L}}\\p{{N}} ]', ' ', 'g'), ' +', ' ', 'g'))"
_PLAIN = "lower(regexp_replace(text, '[\\r\\n]+', ' ', 'g'))"
for _a in notes.ABBREVIATIONS:
    _PLAIN = f"replace({_PLAIN}, '{_a}', '{_a.replace('.', '')}')"
_CLEANED = _CLEAN.format(t=_PLAIN)
_WORDS = f"w AS (SELECT doc_id, list_filter(string_split({_CLEANED}, ' '), lambda x: x <> '') AS words FROM documents)"


@query("n_category", "SELECT source AS category, count(*) AS n FROM documents WHERE source IN ('src0', 'src1') GROUP BY source")
def _(s, d):
    return notes.select_category(retail.notes(s, d), ["src0", "src1"]).groupBy("category").agg(F.count("*").alias("n"))


@query("n_clean", f"SELECT doc_id AS note_id, md5({_CLEANED}) AS digest FROM documents")
def _(s, d):
    return retail.notes(s, d).select("note_id", F.md5(notes.clean(F.col("text"))).alias("digest"))


def _chunks(s, d):
    return notes.chunk(retail.notes(s, d).withColumn("text", notes.clean(F.col("text"))))


_CHUNKS = _WORDS + ", c AS (SELECT doc_id AS note_id, words, unnest(range(0, CAST(ceil(len(words) / 512.0) AS BIGINT))) AS i FROM w WHERE len(words) > 0)"


@query("n_chunk", f"WITH {_CHUNKS} SELECT note_id, CAST(i AS INTEGER) AS chunk_no, CAST(ceil(len(words) / 512.0) AS INTEGER) AS n_chunks, md5(array_to_string(words[i * 512 + 1:i * 512 + 512], ' ')) AS digest, CAST(len(words[i * 512 + 1:i * 512 + 512]) AS INTEGER) AS n_tokens FROM c")
def _(s, d):
    return _chunks(s, d).select("note_id", "chunk_no", "n_chunks", F.md5("text").alias("digest"), "n_tokens")


@query("n_chunk_stats", f"WITH {_CHUNKS}, p AS (SELECT note_id, count(*) AS c FROM c GROUP BY note_id) SELECT count(*) AS n_notes, CAST(sum(c) AS BIGINT) AS n_chunks, max(c) AS max_chunks FROM p")
def _(s, d):
    return notes.chunk_stats(_chunks(s, d))


_MARKUP = "trim(regexp_replace(regexp_replace(regexp_replace(regexp_replace(html, '(?s)<!--.*?-->', ' ', 'g'), '(?is)<(script|style)[^>]*>.*?</(script|style)>', ' ', 'g'), '(?s)<[^>]*>', ' ', 'g'), '\\s+', ' ', 'g'))"


@query("n_markup", f"SELECT page_id, md5({_MARKUP}) AS digest FROM pages")
def _(s, d):
    return load(s, d, "pages", ["page_id", "html"]).select("page_id", F.md5(notes.strip_markup(F.col("html"))).alias("digest"))


#: Closed-form chunk scores: the share of a letter among a chunk's characters, for three classes.
_LETTERS = ("e", "n", "s")


def _chunk_scores(s, d):
    shares = F.explode(F.array(*(F.struct(F.lit(i).alias("class_id"), ((F.length("text") - F.length(F.replace("text", F.lit(c), F.lit("")))) / F.length("text")).alias("p")) for i, c in enumerate(_LETTERS))))
    return _chunks(s, d).select(F.col("note_id").alias("sample_id"), shares.alias("x"), F.lit(0).alias("y")).select("sample_id", "x.class_id", "x.p", "y")


_SCORES = f"WITH {_CHUNKS}, t AS (SELECT note_id, array_to_string(words[i * 512 + 1:i * 512 + 512], ' ') AS text FROM c), sc AS (SELECT note_id, class_id, (length(text) - length(replace(text, letter, ''))) / CAST(length(text) AS DOUBLE) AS p FROM t, (VALUES (0, 'e'), (1, 'n'), (2, 's')) v(class_id, letter))"


def _merge(name, how, expression):
    @query(name, f"{_SCORES} SELECT note_id AS sample_id, class_id, count(*) AS n_chunks, round({expression}, 6) AS p FROM sc GROUP BY note_id, class_id")
    def _(s, d):
        return scoring.merge_chunks(_chunk_scores(s, d), how=how).select("sample_id", "class_id", "n_chunks", F.round("p", 6).alias("p"))


_merge("n_merge_chunks", "blend", "(max(p) + avg(p) * count(*) / 2.0) / (1 + count(*) / 2.0)")
_merge("n_merge_max", "max", "max(p)")
_merge("n_merge_mean", "mean", "avg(p)")


@query("n_pool", "WITH x AS (SELECT label, unnest(embedding) AS v, unnest(range(1, 65)) AS i FROM embeddings), m AS (SELECT label, i, avg(CAST(v AS DOUBLE)) AS v FROM x GROUP BY label, i) SELECT label, i AS dim, round(v, 5) AS v FROM m")
def _(s, d):
    pooled = vectors.pool(load(s, d, "embeddings", ["label", "embedding"]), "label", "embedding")
    return pooled.select("label", F.posexplode("embedding").alias("dim", "v")).select("label", (F.col("dim") + 1).cast("bigint").alias("dim"), F.round("v", 5).alias("v"))


# ---------------------------------------------------------------- datasets and folds


@query("d_return_dataset", ENC + " SELECT visit_id, subject_id, CAST(CASE WHEN prior_discharge IS NULL THEN -1 ELSE greatest(admit - prior_discharge, 0) END AS BIGINT) AS gap, CAST(discharge - admit AS BIGINT) AS stay, y FROM lab")
def _(s, d):
    rows = cohorts.return_dataset(_enc(s, d))
    gap = F.when(F.col("has_prior"), F.col("gap_days")).otherwise(-1)
    return rows.select("visit_id", "subject_id", gap.cast("bigint").alias("gap"), F.col("stay_days").cast("bigint").alias("stay"), F.col("y_return").alias("y"))


@query("d_next_dx_dataset", ENC + DX.format(level=PARENT) + " SELECT q.visit_id, q.subject_id, coalesce(array_to_string(a.codes, ','), '') AS codes, array_to_string(b.codes, ',') AS next_codes FROM seq q LEFT JOIN dx a ON a.visit_id = q.visit_id JOIN dx b ON b.visit_id = q.next_visit")
def _(s, d):
    rows = cohorts.next_dx_dataset(_enc(s, d), _dx(s, d, "parent")[1])
    return rows.select("visit_id", "subject_id", F.array_join("codes", ",").alias("codes"), F.array_join("next_codes", ",").alias("next_codes"))


_PAT = ", pat AS (SELECT subject_id, max(y) AS stratum FROM lab GROUP BY subject_id)"
_FOLD = _PAT + f", fold AS (SELECT subject_id, stratum, CAST((row_number() OVER (PARTITION BY stratum ORDER BY {HASH.format(key='subject_id', seed=42)}, subject_id) - 1) % 10 AS INTEGER) AS fold FROM pat)"


def _folded(s, d):
    return folds.by_subject(cohorts.patient_label(_labelled(s, d)))


@query("d_fold_subject", ENC + _FOLD + " SELECT * FROM fold")
def _(s, d):
    return _folded(s, d)


@query("d_fold_visit", ENC + f" SELECT visit_id, y AS stratum, CAST((row_number() OVER (PARTITION BY y ORDER BY {HASH.format(key='visit_id', seed=42)}, visit_id) - 1) % 10 AS INTEGER) AS fold FROM lab")
def _(s, d):
    return folds.by_visit(_labelled(s, d))


def _rotation(name, n, key):
    """What each rotation of the dealt subjects (or visits) tests, validates and trains on."""
    strata = "PARTITION BY max(y)" if key == "subject_id" else "PARTITION BY y"
    group = " GROUP BY subject_id" if key == "subject_id" else ""
    dealt = f", f AS (SELECT CAST((row_number() OVER ({strata} ORDER BY {HASH.format(key=key, seed=42)}, {key}) - 1) % {n} AS INTEGER) AS fold FROM lab{group})"

    @query(name, ENC + dealt + f" SELECT CAST(i AS INTEGER) AS iter, fold, CASE WHEN fold = i THEN 'test' WHEN fold = (i + 1) % {n} THEN 'validation' ELSE 'train' END AS role, count(*) AS n FROM f, range({n}) a(i) GROUP BY i, fold")
    def _(s, d):
        rows = _labelled(s, d)
        dealt = folds.by_subject(cohorts.patient_label(rows), n) if key == "subject_id" else folds.by_visit(rows, n)
        sizes = dealt.groupBy("fold").agg(F.count("*").alias("n"))
        return sizes.join(F.broadcast(folds.rotation(s, n)), "fold").select("iter", "fold", "role", "n")


_rotation("d_rotation_8_1_1", 10, "subject_id")
_rotation("d_rotation_3_1_1", 5, "visit_id")


def _negatives(seed):
    return f" SELECT visit_id, y AS y_return FROM (SELECT *, row_number() OVER (PARTITION BY y ORDER BY {HASH.format(key='visit_id', seed=seed)}, visit_id) AS r, sum(y) OVER () AS n FROM lab) WHERE y = 1 OR r <= n"


@query("d_balance_iter", ENC + _negatives("42/3"))
def _(s, d):
    return folds.balance(_labelled(s, d), iteration=3).select("visit_id", "y_return")


@query("d_balance_once", ENC + _negatives("42/0"))
def _(s, d):
    return folds.balance_once(_labelled(s, d)).select("visit_id", "y_return")


def _roles(s, d, by="subject"):
    rows = _labelled(s, d).select("subject_id", "visit_id", "y_return")
    dealt = rows.join(_folded(s, d).select("subject_id", "fold"), "subject_id") if by == "subject" else rows.join(folds.by_visit(rows).select("visit_id", "fold"), "visit_id")
    return dealt.join(F.broadcast(folds.rotation(s, 10)), "fold")


@query("d_audit_subject", "SELECT CAST(0 AS INTEGER) AS iter, CAST(0 AS BIGINT) AS subject_id, CAST(0 AS BIGINT) AS roles WHERE false")
def _(s, d):
    return folds.audit_subjects(_roles(s, d))


@query("d_audit_visit_folds", ENC + f", vf AS (SELECT subject_id, CAST((row_number() OVER (PARTITION BY y ORDER BY {HASH.format(key='visit_id', seed=42)}, visit_id) - 1) % 10 AS INTEGER) AS fold FROM lab), r AS (SELECT i, subject_id, CASE WHEN fold = i THEN 'test' WHEN fold = (i + 1) % 10 THEN 'validation' ELSE 'train' END AS role FROM vf, range(10) a(i)) SELECT CAST(i AS INTEGER) AS iter, count(*) AS crossing FROM (SELECT i, subject_id FROM r GROUP BY i, subject_id HAVING count(DISTINCT role) > 1) GROUP BY i")
def _(s, d):
    return folds.audit_subjects(_roles(s, d, "visit")).groupBy("iter").agg(F.count("*").alias("crossing"))


@query("d_audit_never_tested", "SELECT o_orderkey AS visit_id FROM orders WHERE false")
def _(s, d):
    return folds.audit_never_tested(_enc(s, d), _roles(s, d))


_GRAMS = "(SELECT DISTINCT {k} AS k, array_to_string(ws[i + 1:i + 8], ' ') AS g FROM (SELECT {k}, ws, unnest(range(0, len(ws) - 7)) AS i FROM (SELECT {k}, list_filter(string_split_regex(lower(text), '\\s+'), lambda x: x <> '') AS ws FROM {t}) WHERE len(ws) >= 8))"


@query("d_text_overlap", f"SELECT a.k AS doc_id, b.k AS item_id, count(*) AS shared FROM {_GRAMS.format(k='doc_id', t='documents')} a JOIN {_GRAMS.format(k='item_id', t='benchmark')} b USING (g) GROUP BY 1, 2")
def _(s, d):
    return folds.text_overlap(load(s, d, "documents", ["doc_id", "text"]), load(s, d, "benchmark"))


@query("d_fold_report", ENC + _FOLD + " SELECT coalesce(CAST(fold AS INTEGER), -1) AS fold, coalesce(y, -1) AS y, count(*) AS visits, count(DISTINCT subject_id) AS patients FROM lab JOIN fold USING (subject_id) GROUP BY ROLLUP (fold, y)")
def _(s, d):
    rows = _labelled(s, d).join(_folded(s, d).select("subject_id", "fold"), "subject_id")
    return folds.report(rows).select(F.coalesce("fold", F.lit(-1)).alias("fold"), F.coalesce("y_return", F.lit(-1)).alias("y"), "visits", "patients")


@query("d_holdout", ENC + ", r AS (SELECT visit_id, CAST(i AS INTEGER) AS run FROM enc, range(3) a(i)) SELECT run, count(*) AS n, CAST(sum(CASE WHEN ('0x' || substr(md5(visit_id || '/' || run || '/42'), 1, 8))::BIGINT / 4294967296.0::DOUBLE < 0.15::DOUBLE THEN 1 ELSE 0 END) AS BIGINT) AS validation FROM r GROUP BY run")
def _(s, d):
    return folds.random_holdout(_enc(s, d)).groupBy("run").agg(F.count("*").alias("n"), F.sum((F.col("split") == "validation").cast("bigint")).alias("validation"))


@query("d_label_split")
def _(s, d):
    samples = _dx(s, d)[1].select(F.col("visit_id").alias("key"), F.col("codes").alias("labels"))
    return folds.iterative_label_split(samples, {"train": 8, "validation": 1, "test": 1})


@query("d_expand", ENC + _FOLD + " SELECT visit_id, lab.subject_id, y AS y_return, fold FROM lab JOIN fold ON lab.subject_id = fold.subject_id")
def _(s, d):
    return folds.expand(_folded(s, d), _labelled(s, d)).select("visit_id", "subject_id", "y_return", "fold")


# ---------------------------------------------------------------- sequences


def _slide(name, k, partial="short_only"):
    keep = {"short_only": f"pos >= {k} OR (m - 1 < {k} AND pos = m - 1)", "all": "true"}[partial]

    @query(name, ENC + f", x AS (SELECT *, list(visit_id) OVER (PARTITION BY subject_id ORDER BY admit, visit_id ROWS BETWEEN {k - 1} PRECEDING AND CURRENT ROW) AS ids FROM seq) SELECT subject_id, next_visit AS target_visit, array_to_string(ids, ',') AS visits, CAST(len(ids) AS INTEGER) AS n FROM x WHERE next_visit IS NOT NULL AND ({keep})")
    def _(s, d):
        real = F.filter("visit_ids", lambda v: v.isNotNull()).cast("array<string>")
        return sequences.sliding(_enc(s, d), k, partial).select("subject_id", "target_visit", F.array_join(real, ",").alias("visits"), "n")


_slide("q_slide3", 3)
_slide("q_slide6", 6)
_slide("q_slide_partial_all", 3, "all")


@query("q_prepare", ENC + " SELECT visit_id, pos, m FROM seq WHERE m > 1")
def _(s, d):
    return sequences.prepare(_enc(s, d)).select("visit_id", F.col("pos").cast("bigint").alias("pos"), "m")


@query("q_prefixes", ENC + ", x AS (SELECT *, list(visit_id) OVER (PARTITION BY subject_id ORDER BY admit, visit_id) AS ids FROM seq) SELECT subject_id, next_visit AS target_visit, array_to_string(ids, ',') AS visits FROM x WHERE next_visit IS NOT NULL")
def _(s, d):
    return sequences.prefixes(_enc(s, d)).select("subject_id", "target_visit", F.array_join(F.col("visit_ids").cast("array<string>"), ",").alias("visits"))


@query("q_counts", ENC + ", p AS (SELECT subject_id, count(*) - 1 AS m FROM enc GROUP BY subject_id), q AS (SELECT * FROM p WHERE m > 0), r AS (SELECT CAST(sum(greatest(m - 2, 1)) AS BIGINT) AS a, CAST(sum(greatest(m - 5, 1)) AS BIGINT) AS b, CAST(sum(m) AS BIGINT) AS c, CAST(sum(m * (m + 1) / 2) AS BIGINT) AS e FROM q) SELECT unnest(['sliding_3', 'sliding_6', 'prefixes', 'prefix_cells']) AS scheme, unnest([a, b, c, e]) AS samples FROM r")
def _(s, d):
    return sequences.count_report(_enc(s, d))


# ---------------------------------------------------------------- functions of models, as columns

_LOGITS = "z AS (SELECT vec_id AS sample_id, unnest(embedding) AS z, unnest(range(0, 64)) AS class_id, label FROM embeddings)"


def _logits(s, d):
    e = load(s, d, "embeddings")
    return e.select(F.col("vec_id").alias("sample_id"), "label", F.posexplode("embedding").alias("class_id", "z")).withColumn("z", F.col("z").cast("double"))


@query("m_sigmoid", f"WITH {_LOGITS} SELECT sample_id, class_id, round(1 / (1 + exp(-CAST(z AS DOUBLE))), 6) AS p FROM z")
def _(s, d):
    return _logits(s, d).select("sample_id", F.col("class_id").cast("bigint").alias("class_id"), F.round(scoring.sigmoid(F.col("z")), 6).alias("p"))


@query("m_softmax", f"WITH {_LOGITS} SELECT sample_id, class_id, round(exp(CAST(z AS DOUBLE)) / sum(exp(CAST(z AS DOUBLE))) OVER (PARTITION BY sample_id), 6) AS p FROM z")
def _(s, d):
    return scoring.softmax(_logits(s, d)).select("sample_id", F.col("class_id").cast("bigint").alias("class_id"), F.round("p", 6).alias("p"))


@query("m_bce", f"WITH {_LOGITS}, p AS (SELECT 1 / (1 + exp(-CAST(z AS DOUBLE))) AS p, CASE WHEN class_id = label THEN 1 ELSE 0 END AS y FROM z) SELECT round(avg(-(y * ln(p) + (1 - y) * ln(1 - p))), 6) AS bce FROM p")
def _(s, d):
    rows = _logits(s, d).select(scoring.sigmoid(F.col("z")).alias("p"), (F.col("class_id") == F.col("label")).cast("int").alias("y"))
    return metrics.bce(rows).select(F.round("bce", 6).alias("bce"))


@query("m_ce", f"WITH {_LOGITS}, p AS (SELECT sample_id, class_id, label, exp(CAST(z AS DOUBLE)) / sum(exp(CAST(z AS DOUBLE))) OVER (PARTITION BY sample_id) AS p FROM z) SELECT round(sum(-ln(p)) / count(*), 6) AS ce FROM p WHERE class_id = label")
def _(s, d):
    rows = scoring.softmax(_logits(s, d)).withColumn("y", (F.col("class_id") == F.col("label")).cast("int"))
    return metrics.ce(rows).select(F.round("ce", 6).alias("ce"))


@query("m_mish", f"WITH {_LOGITS}, t AS (SELECT sample_id, class_id, CAST(z AS DOUBLE) AS z FROM z) SELECT sample_id, class_id, round(z * (exp(2 * ln(1 + exp(z))) - 1) / (exp(2 * ln(1 + exp(z))) + 1), 6) AS v FROM t")
def _(s, d):
    return _logits(s, d).select("sample_id", F.col("class_id").cast("bigint").alias("class_id"), F.round(scoring.mish(F.col("z")), 6).alias("v"))


@query("m_layer_norm", f"WITH {_LOGITS}, t AS (SELECT sample_id, class_id, CAST(z AS DOUBLE) AS z FROM z) SELECT sample_id, class_id, round((z - avg(z) OVER w) / sqrt(var_pop(z) OVER w + 0.00001), 5) AS v FROM t WINDOW w AS (PARTITION BY sample_id)")
def _(s, d):
    e = load(s, d, "embeddings").select(F.col("vec_id").alias("sample_id"), F.posexplode(scoring.layer_norm(F.col("embedding").cast("array<double>"))).alias("class_id", "v"))
    return e.select("sample_id", F.col("class_id").cast("bigint").alias("class_id"), F.round("v", 5).alias("v"))


@query("m_linear_head", f"WITH {_LOGITS} SELECT sample_id, round(sum(CAST(z AS DOUBLE) * (class_id % 5 - 2)) + 0.5, 5) AS v FROM z GROUP BY sample_id")
def _(s, d):
    return load(s, d, "embeddings").select(F.col("vec_id").alias("sample_id"), F.round(scoring.linear(F.col("embedding").cast("array<double>"), [i % 5 - 2 for i in range(64)], 0.5), 5).alias("v"))


# ---------------------------------------------------------------- measures, on closed-form scores

_PREV = ENC + DX.format(level=BRAND) + """, pr AS (SELECT q.visit_id AS sample_id, coalesce(a.codes, []) AS x, b.codes AS y FROM seq q LEFT JOIN dx a ON a.visit_id = q.visit_id JOIN dx b ON b.visit_id = q.next_visit),
prior AS (SELECT code AS class_id, count(*) / CAST((SELECT count(*) FROM pr) AS DOUBLE) AS prior FROM (SELECT unnest(y) AS code FROM pr) GROUP BY code),
sc AS (SELECT sample_id, class_id, CASE WHEN list_contains(y, class_id) THEN 1 ELSE 0 END AS y, 0.5::DOUBLE * prior + CASE WHEN list_contains(x, class_id) THEN 0.5::DOUBLE ELSE 0.0::DOUBLE END AS p FROM pr, prior)"""


def _scores(s, d):
    rows = cohorts.next_codes_label(_enc(s, d), _dx(s, d)[1]).select(F.col("visit_id").alias("sample_id"), F.col("codes").alias("x"), F.col("next_codes").alias("y"))
    return scoring.prevalence_scorer(rows, rows)


_RISK = ENC + ", sc AS (SELECT visit_id AS sample_id, y, 1 / (1 + CASE WHEN prior_discharge IS NULL THEN 365 ELSE greatest(admit - prior_discharge, 0) END + CAST(discharge - admit AS DOUBLE)) AS p FROM lab)"


def _risk(s, d):
    rows = temporal.return_label(temporal.stay_length(temporal.prior_gap(_enc(s, d), first_fill=365)))
    return rows.select(F.col("visit_id").alias("sample_id"), F.lit(0).alias("class_id"), F.col("y_return").alias("y"), (1 / (1 + F.col("gap_days") + F.col("stay_days").cast("double"))).alias("p"))


_CURVE = ", cu AS (SELECT p, CAST(sum(y) AS DOUBLE) AS pos, CAST(sum(1 - y) AS DOUBLE) AS neg FROM sc GROUP BY p), cv AS (SELECT *, sum(pos) OVER w AS tp, sum(neg) OVER w AS fp, sum(pos) OVER () AS ap, sum(neg) OVER () AS an FROM cu WINDOW w AS (ORDER BY p DESC))"
_REPORT = "CAST(count(*) FILTER (p >= {t} AND y = 1) AS BIGINT) AS tp, CAST(count(*) FILTER (p >= {t} AND y = 0) AS BIGINT) AS fp, CAST(count(*) FILTER (p < {t} AND y = 1) AS BIGINT) AS fn"
_RATIOS = "CASE WHEN tp + fp > 0 THEN tp / CAST(tp + fp AS DOUBLE) ELSE 0 END AS precision, CASE WHEN tp + fn > 0 THEN tp / CAST(tp + fn AS DOUBLE) ELSE 0 END AS recall, CASE WHEN tp > 0 THEN 2 * tp / CAST(2 * tp + fp + fn AS DOUBLE) ELSE 0 END AS f1"


def _rounded(df, *names):
    return df.select(*[c for c in df.columns if c not in names], *(F.round(n, 6).alias(n) for n in names))


@query("a_threshold_micro", f"{_PREV}, r AS (SELECT {_REPORT.format(t=0.5)} FROM sc), q AS (SELECT tp, fp, fn, {_RATIOS} FROM r) SELECT tp, fp, fn, round(precision, 6) AS precision, round(recall, 6) AS recall, round(f1, 6) AS f1 FROM q")
def _(s, d):
    return _rounded(metrics.threshold_report(_scores(s, d)), "precision", "recall", "f1")


@query("a_threshold_macro", f"{_PREV}, r AS (SELECT class_id, {_REPORT.format(t=0.5)} FROM sc GROUP BY class_id), q AS (SELECT {_RATIOS} FROM r WHERE tp + fn > 0) SELECT round(avg(precision), 6) AS precision, round(avg(recall), 6) AS recall, round(avg(f1), 6) AS f1, count(*) AS classes FROM q")
def _(s, d):
    return _rounded(metrics.macro_threshold(_scores(s, d)), "precision", "recall", "f1")


@query("a_roc_auc", f"{_RISK}{_CURVE} SELECT round(sum(neg * (tp - pos / 2)) / (max(ap) * max(an)), 6) AS auc FROM cv")
def _(s, d):
    return _rounded(metrics.roc_auc(_risk(s, d)), "auc")


@query("a_pr_auc", f"{_PREV}{_CURVE} SELECT round(sum(tp / (tp + fp) * pos / ap), 6) AS aupr FROM cv")
def _(s, d):
    return _rounded(metrics.pr_auc(_scores(s, d)), "aupr")


@query("a_pr_auc_trapezoid", f"{_RISK}{_CURVE}, t AS (SELECT *, tp / (tp + fp) AS prec FROM cv), u AS (SELECT *, (prec + coalesce(lag(prec) OVER (ORDER BY p DESC), prec)) / 2 AS mid FROM t) SELECT round(sum(mid * pos / ap), 6) AS aupr FROM u")
def _(s, d):
    return _rounded(metrics.pr_auc(_risk(s, d), kind="trapezoid"), "aupr")


@query("a_rp80", f"{_PREV}{_CURVE} SELECT round(coalesce(max(CASE WHEN tp >= 0.3 * (tp + fp) THEN tp / ap END), 0), 6) AS rp FROM cv")
def _(s, d):
    return _rounded(metrics.recall_at_precision(_scores(s, d), 0.3), "rp")


@query("a_rp80_macro", f"{_PREV}, cu AS (SELECT class_id, p, CAST(sum(y) AS DOUBLE) AS pos, CAST(sum(1 - y) AS DOUBLE) AS neg FROM sc GROUP BY class_id, p), cv AS (SELECT class_id, sum(pos) OVER w AS tp, sum(neg) OVER w AS fp, sum(pos) OVER (PARTITION BY class_id) AS ap FROM cu WINDOW w AS (PARTITION BY class_id ORDER BY p DESC)), r AS (SELECT class_id, coalesce(max(CASE WHEN tp >= 0.3 * (tp + fp) THEN tp / ap END), 0) AS rp FROM cv WHERE ap > 0 GROUP BY class_id) SELECT round(avg(rp), 6) AS rp FROM r")
def _(s, d):
    return _rounded(metrics.macro_recall_at_precision(_scores(s, d), 0.3), "rp")


_AT_K = ", rk AS (SELECT *, row_number() OVER (PARTITION BY sample_id ORDER BY p DESC, class_id) AS r FROM sc), e AS (SELECT sample_id, sum(y) AS t, sum(CASE WHEN r <= 3 THEN y ELSE 0 END) AS h3, sum(CASE WHEN r <= 5 THEN y ELSE 0 END) AS h5, sum(CASE WHEN r <= 10 THEN y ELSE 0 END) AS h10 FROM rk GROUP BY sample_id) SELECT round(avg(h3 / CAST(t AS DOUBLE)), 6) AS recall_3, round(avg(h5 / CAST(t AS DOUBLE)), 6) AS recall_5, round(avg(h10 / CAST(t AS DOUBLE)), 6) AS recall_10 FROM e WHERE t > 0"


@query("a_recall_at_k", _PREV + _AT_K)
def _(s, d):
    return _rounded(metrics.recall_at_k(_scores(s, d), (3, 5, 10)), "recall_3", "recall_5", "recall_10")


@query("a_over_folds", f"{ENC}{_FOLD}, sc AS (SELECT fold, y, 1 / (1 + CASE WHEN prior_discharge IS NULL THEN 365 ELSE greatest(admit - prior_discharge, 0) END + CAST(discharge - admit AS DOUBLE)) AS p FROM lab JOIN fold USING (subject_id)), cu AS (SELECT fold, p, CAST(sum(y) AS DOUBLE) AS pos, CAST(sum(1 - y) AS DOUBLE) AS neg FROM sc GROUP BY fold, p), cv AS (SELECT fold, pos, neg, sum(pos) OVER w AS tp, sum(pos) OVER v AS ap, sum(neg) OVER v AS an FROM cu WINDOW w AS (PARTITION BY fold ORDER BY p DESC), v AS (PARTITION BY fold)), a AS (SELECT fold, sum(neg * (tp - pos / 2)) / (max(ap) * max(an)) AS auc FROM cv GROUP BY fold) SELECT 'closed form' AS config, round(avg(auc), 6) AS auc_mean, round(stddev_samp(auc), 6) AS auc_std, count(*) AS folds FROM a")
def _(s, d):
    rows = _risk(s, d).join(_enc(s, d).select(F.col("visit_id").alias("sample_id"), "subject_id"), "sample_id").join(_folded(s, d).select("subject_id", "fold"), "subject_id")
    each = metrics.roc_auc(rows, ["fold"]).withColumn("config", F.lit("closed form"))
    return _rounded(metrics.over_folds(each, "config", ["auc"]), "auc_mean", "auc_std")


@query("a_compare", f"{_PREV}, r AS (SELECT t, {_REPORT.replace('{t}', 't')} FROM sc, (VALUES (0.3::DOUBLE), (0.5::DOUBLE)) v(t) GROUP BY t), q AS (SELECT t, {_RATIOS} FROM r) SELECT a.t AS t, round((a.f1 - b.f1) * 100, 5) AS f1_points, round((a.f1 / b.f1 - 1) * 100, 5) AS f1_percent FROM q a, q b WHERE b.t = 0.5")
def _(s, d):
    scores = _scores(s, d)
    runs = metrics.threshold_report(scores, 0.3).withColumn("t", F.lit(0.3)).unionByName(metrics.threshold_report(scores, 0.5).withColumn("t", F.lit(0.5)))
    out = metrics.compare(runs, "t", 0.5, ["f1"])
    return out.select("t", F.round("f1_points", 5).alias("f1_points"), F.round("f1_percent", 5).alias("f1_percent"))


# ---------------------------------------------------------------- events and turns

_SESS = "WITH a AS (SELECT *, lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS before FROM events), b AS (SELECT *, sum(CASE WHEN before IS NULL OR ts - before >= INTERVAL 6 HOUR THEN 1 ELSE 0 END) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS UNBOUNDED PRECEDING) AS s FROM a), ses AS (SELECT user_id AS subject_id, s, min(event_id) AS visit_id, min(ts) AS admit_ts, max(ts) AS discharge_ts, count(*) AS n_events FROM b GROUP BY user_id, s)"


def _sessions(s, d):
    return EV.sessions(load(s, d, "events"))


@query("e_sessions", _SESS + " SELECT subject_id, visit_id, epoch_us(admit_ts) AS admit_us, epoch_us(discharge_ts) AS discharge_us, n_events FROM ses")
def _(s, d):
    us = lambda c: F.unix_micros(F.col(c).cast("timestamp"))
    return _sessions(s, d).select("subject_id", "visit_id", us("admit_ts").alias("admit_us"), us("discharge_ts").alias("discharge_us"), "n_events")


@query("e_session_returns", _SESS + " SELECT visit_id, CASE WHEN date_diff('day', CAST(discharge_ts AS DATE), CAST(lead(admit_ts) OVER (PARTITION BY subject_id ORDER BY admit_ts, visit_id) AS DATE)) < 7 THEN 1 ELSE 0 END AS y_return FROM ses")
def _(s, d):
    return temporal.return_label(_sessions(s, d).withColumn("urgency", F.lit("")), days=7).select("visit_id", "y_return")


@query("e_session_windows", _SESS + ", q AS (SELECT subject_id, lead(visit_id) OVER w AS target_visit, row_number() OVER w AS pos, list(visit_id) OVER (PARTITION BY subject_id ORDER BY admit_ts, visit_id ROWS BETWEEN 2 PRECEDING AND CURRENT ROW) AS ids FROM ses WINDOW w AS (PARTITION BY subject_id ORDER BY admit_ts, visit_id)) SELECT subject_id, target_visit, array_to_string(ids, ',') AS visits FROM q WHERE target_visit IS NOT NULL AND pos >= 3")
def _(s, d):
    w = sequences.sliding(_sessions(s, d), 3, partial="none")
    return w.select("subject_id", "target_visit", F.array_join(F.col("visit_ids").cast("array<string>"), ",").alias("visits"))


@query("e_session_codes", _SESS + " SELECT visit_id, string_agg(event_type, ',' ORDER BY ts, event_id) AS codes FROM (SELECT b.*, ses.visit_id FROM b JOIN ses ON ses.subject_id = b.user_id AND ses.s = b.s) GROUP BY visit_id")
def _(s, d):
    ev = load(s, d, "events")
    return C.ordered_list(EV.session_codes(ev, EV.sessions(ev))).select("visit_id", F.array_join("codes", ",").alias("codes"))


@query("x_turn_windows", "WITH t AS (SELECT conv_id, turn, role, lead(role) OVER w AS next_role, row_number() OVER w AS pos, list(role) OVER (PARTITION BY conv_id ORDER BY turn ROWS BETWEEN 2 PRECEDING AND CURRENT ROW) AS roles FROM conversations WINDOW w AS (PARTITION BY conv_id ORDER BY turn)) SELECT conv_id, turn, array_to_string(roles, ',') AS roles, next_role FROM t WHERE pos >= 3 AND next_role IS NOT NULL")
def _(s, d):
    t = EV.turns(s, d).withColumn("admit_ts", F.col("admit_seq"))
    w = sequences.sliding(t, 3, partial="none", carry=["role"])
    last = F.element_at("visit_ids", -1)
    nxt = t.select(F.col("subject_id"), F.col("visit_id").alias("target_visit"), F.col("role").alias("next_role"))
    return w.select("subject_id", "target_visit", last.alias("turn"), F.array_join("role", ",").alias("roles")).join(nxt, ["subject_id", "target_visit"]).select(F.col("subject_id").alias("conv_id"), "turn", "roles", "next_role")


@query("e_tumbling", "SELECT epoch_us(time_bucket(INTERVAL 1 DAY, ts)) AS start_us, event_type, count(*) AS n, round(sum(value), 4) AS value FROM events GROUP BY 1, 2")
def _(s, d):
    e = load(s, d, "events").withColumn("ts", F.col("ts").cast("timestamp"))
    return SW.tumbling(e).select(F.unix_micros("start").alias("start_us"), "event_type", "n", F.round("value", 4).alias("value"))


@query("e_hopping", "SELECT epoch_us(CAST(CAST(ts AS DATE) - CAST(i AS INTEGER) AS TIMESTAMP)) AS start_us, event_type, count(*) AS n FROM events, range(7) a(i) GROUP BY 1, 2")
def _(s, d):
    e = load(s, d, "events").withColumn("ts", F.col("ts").cast("timestamp"))
    return SW.hopping(e).select(F.unix_micros("start").alias("start_us"), "event_type", "n")


# ---------------------------------------------------------------- vectors


@query("v_norms", "SELECT vec_id, round(sqrt(list_sum(list_transform(embedding, lambda x: CAST(x AS DOUBLE) * CAST(x AS DOUBLE)))), 5) AS n FROM embeddings")
def _(s, d):
    return load(s, d, "embeddings").select("vec_id", F.round(vectors.norm(F.col("embedding")), 5).alias("n"))


@query("v_cosine_topk", "WITH q AS (SELECT vec_id AS query_id, embedding::DOUBLE[] AS a FROM embeddings WHERE vec_id % 100 = 0), p AS (SELECT query_id, vec_id, list_cosine_similarity(a, embedding::DOUBLE[]) AS c FROM q, embeddings WHERE query_id <> vec_id), r AS (SELECT *, row_number() OVER (PARTITION BY query_id ORDER BY c DESC, vec_id) AS rank FROM p) SELECT query_id, vec_id, rank, round(c, 5) AS similarity FROM r WHERE rank <= 5")
def _(s, d):
    e = load(s, d, "embeddings")
    return vectors.nearest(e, e.filter("vec_id % 100 = 0"), 5).select("query_id", "vec_id", F.col("rank").cast("bigint").alias("rank"), F.round("similarity", 5).alias("similarity"))


@query("v_nearest_lsh")
def _(s, d):
    e = load(s, d, "embeddings")
    return vectors.nearest_lsh(e, e.filter("vec_id % 100 = 0"), 1.35, bucket=2.0)
