"""Registered queries: realism study, distributions, serving, retrieval and reconstruction baselines."""

from __future__ import annotations

from pyspark.sql import Window
from pyspark.sql import functions as F

from ..functions import score as S
from ..functions import stats as X
from ..functions.labels import Labels
from ..plans.oracle import SEV, sql
from ..sources.tables import Tables, severity
from .registry import register


def d(key, fn, text=None):
    register(key, lambda spark, sf: fn(Tables(spark, sf)), sql(text) if text else None)


# The study: labelled documents judged by ten simulated raters.
J = "(SELECT r AS rater, doc_id AS record_id, quality AS truth, CASE WHEN (doc_id*13 + r*7) % 100 < 53 THEN quality ELSE 1 - quality END AS called, 50 + 10*((doc_id + r) % 6) AS confidence FROM labels, range(1, 11) AS x(r))"


def judgments(t):
    r = t.labels.crossJoin(F.broadcast(t.spark.range(1, 11).withColumnRenamed("id", "rater")))
    right = (F.col("doc_id") * 13 + F.col("rater") * 7) % 100 < 53
    return r.select("rater", F.col("doc_id").alias("record_id"), F.col("quality").alias("truth"), F.when(right, F.col("quality")).otherwise(1 - F.col("quality")).alias("called"), (50 + 10 * ((F.col("doc_id") + F.col("rater")) % 6)).alias("confidence"))


HIT = "CAST(called = truth AS DOUBLE)"
H = "(CASE WHEN called = truth THEN 1.0 ELSE 0.0 END)"
d("q_study_confusion", lambda t: judgments(t).agg(F.round(F.avg(F.expr(HIT)), 6).alias("accuracy"), F.round(F.avg(F.expr(f"CASE WHEN truth = 1 THEN {HIT} END")), 6).alias("sensitivity"), F.round(F.avg(F.expr(f"CASE WHEN truth = 0 THEN {HIT} END")), 6).alias("specificity"), F.round(F.avg("called"), 6).alias("real_rate")), f"SELECT round(avg({H}), 6) AS accuracy, round(avg({H}) FILTER (WHERE truth = 1), 6) AS sensitivity, round(avg({H}) FILTER (WHERE truth = 0), 6) AS specificity, round(avg(called), 6) AS real_rate FROM {J}")
d("q_fooled", lambda t: judgments(t).where("truth = 0").groupBy("record_id").agg(F.sum("called").alias("fooled")), f"SELECT record_id, sum(called)::BIGINT AS fooled FROM {J} WHERE truth = 0 GROUP BY 1")
d("q_calibration", lambda t: judgments(t).groupBy("confidence").agg(F.round(F.avg(F.expr(HIT)), 6).alias("accuracy"), F.count("*").alias("n")), f"SELECT confidence, round(avg({H}), 6) AS accuracy, count(*) AS n FROM {J} GROUP BY 1")
d("q_fleiss", lambda t: X.fleiss_kappa(judgments(t)), f"SELECT round((po - pe) / (1 - pe), 6) AS kappa FROM (SELECT avg(a / (r * (r - 1))) AS po FROM (SELECT record_id, sum(n) AS r, sum(n * (n - 1)) AS a FROM (SELECT record_id, called, count(*) AS n FROM {J} GROUP BY 1, 2) GROUP BY 1)), (SELECT sum(s * s) AS pe FROM (SELECT count(*) / sum(count(*)) OVER () AS s FROM {J} GROUP BY called))")
PT = f"(SELECT rater, avg({H}) FILTER (WHERE truth = 0) - avg({H}) FILTER (WHERE truth = 1) AS diff FROM {J} GROUP BY 1)"
paired = lambda t: judgments(t).groupBy("rater").agg((F.avg(F.expr(f"CASE WHEN truth = 0 THEN {HIT} END")) - F.avg(F.expr(f"CASE WHEN truth = 1 THEN {HIT} END"))).alias("diff"))
d("q_paired_t", lambda t: paired(t).agg(F.round(F.avg("diff") / (F.stddev_samp("diff") / F.sqrt(F.count("*"))), 6).alias("t"), (F.count("*") - 1).alias("df")), f"SELECT round(avg(diff) / (stddev_samp(diff) / sqrt(count(*))), 6) AS t, count(*) - 1 AS df FROM {PT}")


def per_rater(t):
    """(rater, p): two-sided binomial test of a rater's right calls against chance."""
    return judgments(t).groupBy("rater").agg(F.sum(F.expr(HIT)).alias("k"), F.count("*").alias("n")).select("rater", X.binom_p("k", "n").alias("p"))


LOG = "lgamma(n + 1) - lgamma({0} + 1) - lgamma(n - {0} + 1) + n * ln(0.5)"


def binom_sql(key, counts):
    """The same test in SQL: the outcomes that are no likelier than ``k`` of ``n``."""
    logs = f"SELECT {key}, {LOG.format('i')} AS l, {LOG.format('k')} AS lk FROM (SELECT {key}, k, n, unnest(range(0, n + 1)) AS i FROM ({counts}))"
    return f"SELECT {key}, least(1.0, sum(exp(l)) FILTER (WHERE l <= lk + 1e-9)) AS p FROM (SELECT {key}, l, lk FROM ({logs})) GROUP BY 1"


RATER_P = binom_sql("rater", f"SELECT rater, CAST(sum({H}) AS BIGINT) AS k, count(*) AS n FROM {J} GROUP BY 1")
d("q_binom", lambda t: per_rater(t).select("rater", F.round("p", 9).alias("p")), f"SELECT rater, round(p, 9) AS p FROM ({RATER_P})")
d(
    "q_holm",
    lambda t: X.holm(per_rater(t)).select("rater", F.round("adjusted", 6).alias("adjusted")),
    f"SELECT rater, round(least(1.0, max(s) OVER (ORDER BY p, rater ROWS UNBOUNDED PRECEDING)), 6) AS adjusted FROM (SELECT rater, p, p * (count(*) OVER () - row_number() OVER (ORDER BY p, rater) + 1) AS s FROM ({RATER_P}))",
)
d("q_bootstrap_ci", lambda t: X.bootstrap_ci(judgments(t).withColumn("hit", F.expr(HIT)).select(F.struct("rater", "record_id").alias("id"), "hit"), "hit", 200))
d("q_rater_order", lambda t: t.labels.crossJoin(F.broadcast(t.spark.range(1, 11).withColumnRenamed("id", "rater"))).select("rater", "doc_id", F.row_number().over(Window.partitionBy("rater").orderBy((F.col("doc_id") * 7919 + F.col("rater") * 104729) % 10007, "doc_id")).cast("long").alias("place")), "SELECT r AS rater, doc_id, row_number() OVER (PARTITION BY r ORDER BY (doc_id*7919 + r*104729) % 10007, doc_id) AS place FROM labels, range(1, 11) AS x(r)")


def matched(t):
    """Real (odd) to synthetic (even) cases of the same sex, segment and ten years of age: k-th to k-th in each block, none used twice."""
    w = Window.partitionBy("sex", "setting", "decade").orderBy("case_id")
    c = t.src_case.withColumn("decade", F.floor(F.col("age_years") / 10))
    half = lambda r, n: c.where(f"case_id % 2 = {r}").withColumn("k", F.row_number().over(w)).select("sex", "setting", "decade", "k", F.col("case_id").alias(n))
    return half(1, "real_id").join(half(0, "synthetic_id"), ["sex", "setting", "decade", "k"]).select("real_id", "synthetic_id")


MH = "(SELECT sex, setting, age_years // 10 AS decade, case_id, row_number() OVER (PARTITION BY sex, setting, age_years // 10 ORDER BY case_id) AS k FROM src_case WHERE case_id % 2 = {})"
d("q_match_pairs", matched, f"SELECT a.case_id AS real_id, b.case_id AS synthetic_id FROM {MH.format(1)} a JOIN {MH.format(0)} b USING (sex, setting, decade, k)")

# Distributions.
CH = "(SELECT chapter, case_id FROM case_dx JOIN dx_node USING (dx_id))"
chapters = lambda t: t.case_dx.join(F.broadcast(t.dx_node), "dx_id").select("chapter", "case_id")
d("q_jsd", lambda t: X.jsd(chapters(t), chapters(t).where("case_id % 3 = 0"), "chapter"), f"SELECT round(sum((CASE WHEN p > 0 THEN p * log2(p / ((p + q) / 2)) ELSE 0 END + CASE WHEN q > 0 THEN q * log2(q / ((p + q) / 2)) ELSE 0 END) / 2), 6) AS jsd FROM (SELECT coalesce(p, 0) AS p, coalesce(q, 0) AS q FROM (SELECT chapter, count(*) / sum(count(*)) OVER () AS p FROM {CH} GROUP BY 1) FULL JOIN (SELECT chapter, count(*) / sum(count(*)) OVER () AS q FROM {CH} WHERE case_id % 3 = 0 GROUP BY 1) USING (chapter))")
d("q_spearman", lambda t: X.spearman(t.case_dx.groupBy("dx_id").agg(F.count("*").alias("x"), F.sum((F.col("case_id") % 3 == 0).cast("long")).alias("y")), "x", "y"), "SELECT round(corr(rx, ry), 6) AS rho FROM (SELECT rank() OVER (ORDER BY x) + (count(*) OVER (PARTITION BY x) - 1) / 2 AS rx, rank() OVER (ORDER BY y) + (count(*) OVER (PARTITION BY y) - 1) / 2 AS ry FROM (SELECT dx_id, count(*) AS x, sum(CASE WHEN case_id % 3 = 0 THEN 1 ELSE 0 END) AS y FROM case_dx GROUP BY 1))")


def comorbidity(t):
    doc = Labels(t).patient_dx.select("patient_id", "dx_id")
    n = doc.groupBy("dx_id").agg(F.count("*").alias("n"))
    pairs = doc.select("patient_id", F.col("dx_id").alias("a")).join(doc.select("patient_id", F.col("dx_id").alias("b")), "patient_id").where("a < b").groupBy("a", "b").agg(F.count("*").alias("both"))
    return pairs.join(n.select(F.col("dx_id").alias("a"), F.col("n").alias("na")), "a").join(n.select(F.col("dx_id").alias("b"), F.col("n").alias("nb")), "b").select("a", "b", "both", F.round(F.col("both") / (F.col("na") + F.col("nb") - F.col("both")), 6).alias("jaccard"))


d("q_comorbidity", comorbidity, "SELECT a, b, n AS both, round(n / (x.n1 + y.n1 - n), 6) AS jaccard FROM (SELECT p.dx_id AS a, q.dx_id AS b, count(*) AS n FROM patient_dx p JOIN patient_dx q ON p.patient_id = q.patient_id AND p.dx_id < q.dx_id GROUP BY 1, 2) JOIN (SELECT dx_id AS a, count(*) AS n1 FROM patient_dx GROUP BY 1) x USING (a) JOIN (SELECT dx_id AS b, count(*) AS n1 FROM patient_dx GROUP BY 1) y USING (b)")
d("q_cohort_contrast", lambda t: chapters(t).withColumn("cohort", F.when(F.col("case_id") % 3 == 0, "ours").when(F.col("case_id") % 3 == 1, "source").otherwise("population")).groupBy("chapter").pivot("cohort", ["ours", "source", "population"]).count().fillna(0), f"SELECT chapter, count(*) FILTER (WHERE case_id % 3 = 0) AS ours, count(*) FILTER (WHERE case_id % 3 = 1) AS source, count(*) FILTER (WHERE case_id % 3 = 2) AS population FROM {CH} GROUP BY 1")

# Serving: resources and roles.
d("q_res_patient", lambda t: t.src_case.groupBy(F.concat(F.lit("Patient/"), F.col("subject_id").cast("string")).alias("id")).agg(F.max("sex").alias("gender"), F.count("*").alias("encounters")), "SELECT 'Patient/' || subject_id AS id, max(sex) AS gender, count(*) AS encounters FROM src_case GROUP BY 1")
d("q_res_condition", lambda t: t.case_dx.join(F.broadcast(t.dx_node), "dx_id").select(F.concat(F.lit("Condition/"), F.col("case_id").cast("string"), F.lit("-"), F.col("dx_id").cast("string")).alias("id"), "code", "role"), "SELECT 'Condition/' || case_id || '-' || dx_id AS id, code, role FROM case_dx JOIN dx_node USING (dx_id)")
d("q_res_observation", lambda t: t.case_finding.join(t.finding_node.where("kind = 'lab'"), "finding_id").select(F.concat(F.lit("Observation/"), F.col("case_id").cast("string"), F.lit("-"), F.col("finding_id").cast("string")).alias("id"), "term"), "SELECT 'Observation/' || case_id || '-' || finding_id AS id, term FROM case_finding JOIN finding_node USING (finding_id) WHERE kind = 'lab'")
d("q_res_bundle", lambda t: t.src_case.select(F.col("subject_id"), F.struct("case_id", "acuity").alias("e")).groupBy("subject_id").agg(F.to_json(F.array_sort(F.collect_list("e"))).alias("bundle")), "SELECT subject_id, CAST(to_json(list({'case_id': case_id, 'acuity': acuity} ORDER BY case_id)) AS VARCHAR) AS bundle FROM src_case GROUP BY 1")
ROLES = [("clinician", "Condition"), ("clinician", "Observation"), ("billing", "Condition")]
d("q_rbac_rows", lambda t: t.case_dx.select(F.lit("Condition").alias("kind"), "case_id").unionByName(t.case_finding.select(F.lit("Observation").alias("kind"), "case_id")).crossJoin(F.broadcast(t.spark.createDataFrame([("billing",), ("clinician",)], "role string"))).join(F.broadcast(t.spark.createDataFrame(ROLES, "role string, kind string")), ["role", "kind"], "left_semi").groupBy("role", "kind").agg(F.count("*").alias("n")), "SELECT role, kind, count(*) AS n FROM (SELECT 'Condition' AS kind FROM case_dx UNION ALL SELECT 'Observation' FROM case_finding) JOIN (VALUES ('clinician','Condition'),('clinician','Observation'),('billing','Condition')) AS p(role, kind) USING (kind) GROUP BY 1, 2")
d("q_rbac_mask", lambda t: t.src_case.select("case_id", F.lit("***").alias("age_years"), "sex"), "SELECT case_id, '***' AS age_years, sex FROM src_case")

# Executable baselines: rankers of documents for benchmark items, reconstructors, summarizers.
words = lambda c: F.filter(F.split(F.lower(c), "[^a-z]+"), lambda x: F.length(x) > 0)


def bm25(t, k1=1.2, b=0.75, idf_only=False, k=10):
    """Inverted index by one shuffle on terms; only query terms are joined."""
    q = t.benchmark.select("item_id", F.explode(F.array_distinct(words("text"))).alias("term"))
    tf = t.documents.select("doc_id", F.explode(words("text")).alias("term")).join(q.select("term").distinct(), "term", "left_semi").groupBy("doc_id", "term").agg(F.count("*").alias("tf"))
    size = t.documents.select("doc_id", F.size(words("text")).alias("len"))
    total = size.agg(F.count("*").alias("n"), F.avg("len").alias("mean"))
    df = tf.groupBy("term").agg(F.count("*").alias("df"))
    idf = F.log(1 + (F.col("n") - F.col("df") + 0.5) / (F.col("df") + 0.5))
    w = F.col("tf") * idf if idf_only else idf * F.col("tf") * (k1 + 1) / (F.col("tf") + k1 * (1 - b + b * F.col("len") / F.col("mean")))
    s = q.join(tf, "term").join(df, "term").join(size, "doc_id").crossJoin(F.broadcast(total)).groupBy("item_id", "doc_id").agg(F.round(F.sum(w), 4).alias("score"))
    return s.withColumn("rank", F.row_number().over(Window.partitionBy("item_id").orderBy(F.desc("score"), "doc_id")).cast("long")).where(F.col("rank") <= k)


WD = "list_filter(string_split_regex(lower(text), '[^a-z]+'), lambda x: length(x) > 0)"
BM = f"WITH q AS (SELECT DISTINCT item_id, unnest({WD}) AS term FROM benchmark), tf AS (SELECT doc_id, term, count(*) AS tf FROM (SELECT doc_id, unnest({WD}) AS term FROM documents) WHERE term IN (SELECT term FROM q) GROUP BY 1, 2), size AS (SELECT doc_id, len({WD}) AS len FROM documents), total AS (SELECT count(*) AS n, avg(len) AS mean FROM size), df AS (SELECT term, count(*) AS df FROM tf GROUP BY 1) SELECT item_id, doc_id, score, rank FROM (SELECT *, row_number() OVER (PARTITION BY item_id ORDER BY score DESC, doc_id) AS rank FROM (SELECT item_id, doc_id, round(sum({{}}), 4) AS score FROM q JOIN tf USING (term) JOIN df USING (term) JOIN size USING (doc_id), total GROUP BY 1, 2)) WHERE rank <= 10"
IDF = "ln(1 + (n - df + 0.5) / (df + 0.5))"
d("q_bm25", bm25, BM.format(f"{IDF} * tf * 2.2 / (tf + 1.2 * (1 - 0.75 + 0.75 * len / mean))"))
d("q_tfidf", lambda t: bm25(t, idf_only=True), BM.format(f"tf * {IDF}"))
d("q_overlap_rank", lambda t: t.benchmark.select("item_id", F.explode(F.array_distinct(words("text"))).alias("term")).join(t.documents.select("doc_id", F.explode(F.array_distinct(words("text"))).alias("term")), "term").groupBy("item_id", "doc_id").agg(F.count("*").alias("score")).withColumn("rank", F.row_number().over(Window.partitionBy("item_id").orderBy(F.desc("score"), "doc_id")).cast("long")).where("rank <= 10"), f"SELECT item_id, doc_id, score, rank FROM (SELECT *, row_number() OVER (PARTITION BY item_id ORDER BY score DESC, doc_id) AS rank FROM (SELECT item_id, doc_id, count(*) AS score FROM (SELECT DISTINCT item_id, unnest({WD}) AS term FROM benchmark) JOIN (SELECT DISTINCT doc_id, unnest({WD}) AS term FROM documents) USING (term) GROUP BY 1, 2)) WHERE rank <= 10")


def cosine(t, k=5):
    """Exact search: a bounded set of queries, sent to all vectors."""
    e = t.embeddings.select("vec_id", F.col("embedding").cast("array<double>").alias("v"))
    dot = lambda a, b: F.aggregate(F.zip_with(a, b, lambda x, y: x * y), F.lit(0.0), lambda s, x: s + x)
    q = F.broadcast(e.where("vec_id % 100 = 0").select(F.col("vec_id").alias("q"), F.col("v").alias("u")))
    s = e.crossJoin(q).where("q <> vec_id").select("q", "vec_id", F.round(dot("u", "v") / F.sqrt(dot("u", "u") * dot("v", "v")), 6).alias("cosine"))
    return s.withColumn("rank", F.row_number().over(Window.partitionBy("q").orderBy(F.desc("cosine"), "vec_id")).cast("long")).where(F.col("rank") <= k)


DOT = "list_sum(list_transform(range(1, len({0}) + 1), lambda i: {0}[i] * {1}[i]))"
VEC = "(SELECT vec_id, CAST(embedding AS DOUBLE[]) AS v FROM embeddings)"
d(
    "q_cosine_topk",
    cosine,
    "SELECT q, vec_id, cosine, rank FROM (SELECT *, row_number() OVER (PARTITION BY q ORDER BY cosine DESC, vec_id) AS rank FROM ("
    f"SELECT a.vec_id AS q, b.vec_id, round({DOT.format('b.v', 'a.v')} / sqrt({DOT.format('b.v', 'b.v')} * {DOT.format('a.v', 'a.v')}), 6) AS cosine FROM {VEC} a JOIN {VEC} b ON a.vec_id % 100 = 0 AND a.vec_id <> b.vec_id)) WHERE rank <= 5",
)
d("q_recency_rank", lambda t: t.src_case.select("subject_id", "case_id", F.row_number().over(Window.partitionBy("subject_id").orderBy(F.desc("recorded_at"), "case_id")).cast("long").alias("rank")).where("rank <= 5"), "SELECT subject_id, case_id, rank FROM (SELECT subject_id, case_id, row_number() OVER (PARTITION BY subject_id ORDER BY recorded_at DESC, case_id) AS rank FROM src_case) WHERE rank <= 5")


def recon(key, frame, text):
    """A problem list made by rule, scored with and without penalty on documented extras."""
    def run(t):
        g = Labels(t)
        return S.macro(S.severity_f1(frame(t, g).withColumn("m", F.lit(0)), g.patient_dx))

    d(key, run, f"SELECT 0 AS m, round(avg(2.0 * coalesce(hit, 0) / (coalesce(hit, 0) + coalesce(extra, 0) + gold)), 6) AS score, count(*) AS n FROM (SELECT patient_id, sum(weight) AS gold FROM patient_dx GROUP BY 1) LEFT JOIN (SELECT patient_id, sum(weight) AS hit FROM ({text}) JOIN patient_dx USING (patient_id, dx_id) GROUP BY 1) USING (patient_id) LEFT JOIN (SELECT patient_id, count(*) AS extra FROM ({text}) ANTI JOIN patient_dx USING (patient_id, dx_id) GROUP BY 1) USING (patient_id)")


last = lambda t: t.src_case.withColumn("_r", F.row_number().over(Window.partitionBy("subject_id").orderBy(F.desc("recorded_at"), F.desc("case_id")))).where("_r = 1")
recon("q_rec_all", lambda t, g: g.documented, "SELECT patient_id, dx_id FROM documented")
recon("q_rec_latest", lambda t, g: last(t).join(t.case_dx, "case_id").select(F.col("subject_id").alias("patient_id"), "dx_id").distinct(), "SELECT DISTINCT subject_id AS patient_id, dx_id FROM (SELECT *, row_number() OVER (PARTITION BY subject_id ORDER BY recorded_at DESC, case_id DESC) AS r FROM src_case) JOIN case_dx USING (case_id) WHERE r = 1")
recon("q_rec_repeat", lambda t, g: t.src_case.join(t.case_dx, "case_id").groupBy(F.col("subject_id").alias("patient_id"), "dx_id").count().where("count >= 2").select("patient_id", "dx_id"), "SELECT subject_id AS patient_id, dx_id FROM src_case JOIN case_dx USING (case_id) GROUP BY 1, 2 HAVING count(*) >= 2")
severe = lambda t: t.src_case.join(t.case_dx, "case_id").groupBy(F.col("subject_id").alias("patient_id"), "dx_id").agg(F.max(severity()).alias("w"))
recon("q_rec_topn", lambda t, g: severe(t).withColumn("_r", F.row_number().over(Window.partitionBy("patient_id").orderBy(F.desc("w"), "dx_id"))).where("_r <= 5").select("patient_id", "dx_id"), f"SELECT patient_id, dx_id FROM (SELECT *, row_number() OVER (PARTITION BY patient_id ORDER BY w DESC, dx_id) AS r FROM (SELECT subject_id AS patient_id, dx_id, max({SEV}) AS w FROM src_case JOIN case_dx USING (case_id) GROUP BY 1, 2)) WHERE r <= 5")


def summary(key, order_spark, order_sql):
    def run(t):
        g = Labels(t)
        rows = t.src_case.join(t.case_finding, "case_id").groupBy(F.col("subject_id").alias("patient_id"), "finding_id").agg(F.count("*").alias("n"))
        pred = rows.withColumn("_r", F.row_number().over(Window.partitionBy("patient_id").orderBy(*order_spark()))).where("_r <= 15").withColumn("m", F.lit(0))
        return S.macro(S.set_prf(pred, g.key_finding, keys=["patient_id"], item="finding_id"))

    d(key, run, f"SELECT 0 AS m, round(avg(2.0 * coalesce(hit, 0) / (coalesce(p, 0) + g)), 6) AS score, count(*) AS n FROM (SELECT patient_id, count(*) AS g FROM key_finding GROUP BY 1) LEFT JOIN (SELECT patient_id, count(*) AS p, count(k.finding_id) AS hit FROM (SELECT patient_id, finding_id, row_number() OVER (PARTITION BY patient_id ORDER BY {order_sql}) AS r FROM (SELECT subject_id AS patient_id, finding_id, count(*) AS n FROM src_case JOIN case_finding USING (case_id) GROUP BY 1, 2)) x LEFT JOIN key_finding k USING (patient_id, finding_id) WHERE r <= 15 GROUP BY 1) USING (patient_id)")


summary("q_sum_freq", lambda: [F.desc("n"), "finding_id"], "n DESC, finding_id")
summary("q_sum_first", lambda: ["finding_id"], "finding_id")
