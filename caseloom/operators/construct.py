"""Registered queries: ingest, extraction, grounding, graph, links, clustering, timelines, tasks and splits."""

from __future__ import annotations

from pyspark.sql import Window
from pyspark.sql import functions as F

from ..functions import instances, links, patients, splits
from ..functions import score as S
from ..functions.labels import Labels, Panel
from ..plans.oracle import SEV, sql
from ..sources.tables import Tables, age_bucket, severity
from .registry import register


def d(key, fn, text=None):
    register(key, lambda spark, sf: fn(Tables(spark, sf)), sql(text) if text else None)


day = lambda c: F.date_format(c, "yyyy-MM-dd")
d("q_ingest_cases", lambda t: t.src_case.withColumn("recorded_at", day("recorded_at")), "SELECT * REPLACE (strftime(recorded_at, '%Y-%m-%d') AS recorded_at) FROM src_case")
d("q_ingest_cards", lambda t: t.documents.select(F.col("doc_id").alias("card_id"), "lang", F.length("text").alias("n_chars"), F.size(F.split("text", "\n")).cast("long").alias("n_lines")), "SELECT doc_id AS card_id, lang, length(text) AS n_chars, len(string_split(text, chr(10))) AS n_lines FROM documents")
d("q_ingest_unify", lambda t: t.documents.select(F.lit("card").alias("kind"), F.concat(F.lit("documents:"), F.col("doc_id")).alias("source"), F.md5("text").alias("body")).unionByName(t.conversations.select(F.lit("turn").alias("kind"), F.concat(F.lit("conversations:"), F.col("conv_id"), F.lit(":"), F.col("turn")).alias("source"), F.md5("text").alias("body"))).unionByName(t.benchmark.select(F.lit("item").alias("kind"), F.concat(F.lit("benchmark:"), F.col("item_id")).alias("source"), F.md5("text").alias("body"))), "SELECT 'card' AS kind, 'documents:' || doc_id AS source, md5(text) AS body FROM documents UNION ALL SELECT 'turn', 'conversations:' || conv_id || ':' || turn, md5(text) FROM conversations UNION ALL SELECT 'item', 'benchmark:' || item_id, md5(text) FROM benchmark")
d("q_extract_roles", lambda t: t.case_dx, "SELECT * FROM case_dx")
d("q_extract_findings", lambda t: t.case_finding, "SELECT * FROM case_finding")

# Grounding: distinct surfaces go through the tiers once, each tier sees what earlier ones left.
NORM = "array_to_string(list_sort(string_split(lower(trim(surface)), ' ')), ' ')"


def norm(c):
    return F.array_join(F.array_sort(F.split(F.lower(F.trim(F.col(c))), " ")), " ")


def cascade(mentions, vocab, max_dist=1):
    """(surface, tier, term): exact, normalized, blocked edit distance, else none. [D]

    The vocabulary is a dictionary of bounded size; surfaces are made distinct first.
    """
    terms = F.broadcast(vocab.select("term").distinct())
    left = mentions.select("surface").distinct()
    exact = left.join(terms, left["surface"] == terms["term"]).select("surface", F.lit("exact").alias("tier"), "term")
    left = left.join(exact.select("surface"), "surface", "left_anti")
    normalized = left.withColumn("_n", norm("surface")).join(vocab.select("term").distinct().withColumn("_n", norm("term")).groupBy("_n").agg(F.min("term").alias("term")), "_n").select("surface", F.lit("normalized").alias("tier"), "term")
    left = left.join(normalized.select("surface"), "surface", "left_anti")
    near = left.withColumn("_b", F.substring(F.lower("surface"), 1, 3)).join(vocab.select("term").distinct().withColumn("_b", F.substring(F.lower("term"), 1, 3)), "_b").withColumn("_d", F.levenshtein(F.lower("surface"), F.lower("term"))).where(F.col("_d") <= max_dist)
    fuzzy = near.groupBy("surface").agg(F.min(F.struct("_d", "term"))["term"].alias("term")).select("surface", F.lit("fuzzy").alias("tier"), "term")
    none = left.join(fuzzy.select("surface"), "surface", "left_anti").select("surface", F.lit("none").alias("tier"), F.lit(None).cast("string").alias("term"))
    return exact.unionByName(normalized).unionByName(fuzzy).unionByName(none)


CASC = f"SELECT surface, CASE WHEN e IS NOT NULL THEN 'exact' WHEN n IS NOT NULL THEN 'normalized' WHEN f IS NOT NULL THEN 'fuzzy' ELSE 'none' END AS tier, coalesce(e, n, f) AS term FROM (SELECT surface, (SELECT min(term) FROM finding_node WHERE term = surface) AS e, n, f FROM (SELECT DISTINCT surface, {NORM} AS nn FROM raw_mention) LEFT JOIN (SELECT array_to_string(list_sort(string_split(lower(trim(term)), ' ')), ' ') AS nn, min(term) AS n FROM finding_node GROUP BY 1) USING (nn) LEFT JOIN (SELECT surface, term AS f FROM (SELECT surface, term, row_number() OVER (PARTITION BY surface ORDER BY levenshtein(lower(surface), lower(term)), term) AS rn FROM (SELECT DISTINCT surface FROM raw_mention) JOIN (SELECT DISTINCT term FROM finding_node) ON substr(lower(surface), 1, 3) = substr(lower(term), 1, 3) WHERE levenshtein(lower(surface), lower(term)) <= 1) WHERE rn = 1) USING (surface))"
d("q_ground_cascade", lambda t: cascade(t.raw_mention, t.finding_node), CASC)
d("q_ground_coverage", lambda t: t.raw_mention.join(cascade(t.raw_mention, t.finding_node), "surface").groupBy("tier").agg(F.count("*").alias("n")), f"SELECT tier, count(*) AS n FROM raw_mention JOIN ({CASC}) USING (surface) GROUP BY 1")
d("q_ground_normalized", lambda t: cascade(t.raw_mention, t.finding_node).where("tier = 'normalized'"), f"SELECT * FROM ({CASC}) WHERE tier = 'normalized'")
d("q_ground_fuzzy", lambda t: cascade(t.raw_mention, t.finding_node).where("tier = 'fuzzy'"), f"SELECT * FROM ({CASC}) WHERE tier = 'fuzzy'")
proposed = lambda t: t.dx_node.select("dx_id", F.when(F.col("dx_id") % 4 == 0, F.concat("code", F.lit("X"))).otherwise(F.col("code")).alias("proposed"))
PROP = "(SELECT dx_id, CASE WHEN dx_id % 4 = 0 THEN code || 'X' ELSE code END AS proposed FROM dx_node)"
d("q_ground_code_valid", lambda t: proposed(t).join(F.broadcast(t.dx_node.select(F.col("code").alias("proposed"))), "proposed", "left_semi").select("dx_id", "proposed"), f"SELECT dx_id, proposed FROM {PROP} WHERE proposed IN (SELECT code FROM dx_node)")
d("q_ground_parent", lambda t: proposed(t).join(F.broadcast(t.dx_node.select(F.col("code").alias("proposed"))), "proposed", "left_anti").select("dx_id", F.substring_index("proposed", ".", 1).alias("parent")), f"SELECT dx_id, split_part(proposed, '.', 1) AS parent FROM {PROP} WHERE proposed NOT IN (SELECT code FROM dx_node)")



def grounded(t):
    """(system, surface, tier, term) over three systems: finding terms, diagnosis codes (a code that is not valid falls back to its parent), sites."""
    finding = cascade(t.raw_mention, t.finding_node).withColumn("system", F.lit("finding"))
    codes = F.broadcast(t.dx_node.select(F.col("code").alias("term")))
    code = proposed(t).select(F.col("proposed").alias("surface")).distinct()
    valid = F.col("term").isNotNull()
    code = code.join(codes, F.col("surface") == F.col("term"), "left").select(F.lit("code").alias("system"), "surface", F.when(valid, "exact").otherwise("parent").alias("tier"), F.when(valid, F.col("term")).otherwise(F.substring_index("surface", ".", 1)).alias("term"))
    site = t.part.select(F.upper("p_brand").alias("surface")).distinct()
    sites = t.part.select(F.col("p_brand").alias("term")).distinct().withColumn("_n", F.upper("term"))
    site = site.join(F.broadcast(sites), F.col("surface") == F.col("_n"), "left").select(F.lit("site").alias("system"), "surface", F.when(F.col("term").isNull(), "none").when(F.col("term") == F.col("surface"), "exact").otherwise("normalized").alias("tier"), "term")
    cols = ["system", "surface", "tier", "term"]
    return finding.select(cols).unionByName(code.select(cols)).unionByName(site.select(cols))


GROUND = f"""SELECT 'finding' AS system, surface, tier, term FROM ({CASC})
UNION ALL SELECT DISTINCT 'code', proposed, CASE WHEN code IS NULL THEN 'parent' ELSE 'exact' END, coalesce(code, split_part(proposed, '.', 1)) FROM {PROP} p LEFT JOIN (SELECT code FROM dx_node) n ON n.code = p.proposed
UNION ALL SELECT DISTINCT 'site', upper(p_brand), CASE WHEN upper(p_brand) = p_brand THEN 'exact' ELSE 'normalized' END, p_brand FROM part"""
d("q_ground_all", grounded, GROUND)
d("q_ground_tiers", lambda t: grounded(t).groupBy("system", "tier").agg(F.count("*").alias("n")), f"SELECT system, tier, count(*) AS n FROM ({GROUND}) GROUP BY 1, 2")

node = lambda kind, c: F.concat(F.lit(kind + ":"), F.col(c).cast("string"))
TIERS = ("exact", "normalized", "fuzzy", "none")


def mention_tier(t):
    """(case_id, finding_id, method): the tier that grounded the mention of a finding in a case."""
    return t.raw_mention.select("case_id", "finding_id", "surface").join(cascade(t.raw_mention, t.finding_node).select("surface", F.col("tier").alias("method")), "surface").select("case_id", "finding_id", "method")


def nodes(t):
    """(node, ntype, source, method): every node keeps the row it comes from and how it was grounded."""
    order = F.min(F.expr("CASE method WHEN 'exact' THEN 0 WHEN 'normalized' THEN 1 WHEN 'fuzzy' THEN 2 ELSE 3 END"))
    best = mention_tier(t).groupBy("finding_id").agg(F.element_at(F.array(*map(F.lit, TIERS)), order + 1).alias("method"))
    case = t.case_dx.select("case_id").distinct().select(node("case", "case_id").alias("node"), F.lit("case").alias("ntype"), node("orders", "case_id").alias("source"), F.lit("parsed").alias("method"))
    dx = t.dx_node.select(node("dx", "dx_id").alias("node"), F.lit("dx").alias("ntype"), node("supplier", "dx_id").alias("source"), F.lit("code").alias("method"))
    finding = t.finding_node.join(best, "finding_id", "left").select(node("finding", "finding_id").alias("node"), F.lit("finding").alias("ntype"), node("part", "finding_id").alias("source"), F.coalesce("method", F.lit("unseen")).alias("method"))
    card = t.documents.select(node("card", "doc_id").alias("node"), F.lit("card").alias("ntype"), node("documents", "doc_id").alias("source"), F.lit("parsed").alias("method"))
    return case.unionByName(dx).unionByName(finding).unionByName(card)


def card_links(t):
    """(doc_id, finding_id): a card and the finding concepts (the smallest finding of a term) of whose terms it has a word."""
    token = t.documents.select("doc_id", F.explode(F.array_distinct(F.split(F.lower("text"), "[^a-z]+"))).alias("token"))
    terms = t.finding_node.groupBy("term").agg(F.min("finding_id").alias("finding_id")).select("finding_id", F.explode(F.split("term", " ")).alias("token"))
    return token.join(terms, "token").select("doc_id", "finding_id").distinct()


def edges(t):
    """(src, dst, etype, weight, source, method) of all kinds of edges."""
    cols = lambda src, dst, etype, weight, source, method: [src.alias("src"), dst.alias("dst"), etype.alias("etype"), weight.cast("long").alias("weight"), source.alias("source"), method.alias("method")]
    role = F.expr("CASE role WHEN 'primary' THEN 3 WHEN 'secondary' THEN 2 ELSE 1 END")
    parts = [
        t.case_dx.select(cols(node("case", "case_id"), node("dx", "dx_id"), F.col("role"), role, node("orders", "case_id"), F.lit("extracted"))),
        t.case_finding.join(mention_tier(t), ["case_id", "finding_id"]).select(cols(node("case", "case_id"), node("finding", "finding_id"), F.concat(F.lit("r"), F.col("relevance").cast("string")), F.col("relevance"), node("orders", "case_id"), F.col("method"))),
        t.dx_finding.select(cols(node("dx", "dx_id"), node("finding", "finding_id"), F.col("etype"), F.col("n_cases"), node("supplier", "dx_id"), F.lit("typed"))),
        links.every(t).select(cols(node("dx", "a"), node("dx", "b"), F.lit("related"), F.lit(1), node("supplier", "a"), F.col("method"))),
        card_links(t).select(cols(node("card", "doc_id"), node("finding", "finding_id"), F.lit("mentions"), F.lit(1), node("documents", "doc_id"), F.lit("token"))),
    ]
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return out


MENTION = f"SELECT case_id, finding_id, tier AS method FROM raw_mention JOIN ({CASC}) USING (surface)"
CARD = "SELECT DISTINCT doc_id, finding_id FROM (SELECT doc_id, unnest(string_split_regex(lower(text), '[^a-z]+')) AS token FROM documents) JOIN (SELECT finding_id, unnest(string_split(term, ' ')) AS token FROM (SELECT term, min(finding_id) AS finding_id FROM finding_node GROUP BY 1)) USING (token)"
NODES = f"""SELECT DISTINCT 'case:' || case_id AS node, 'case' AS ntype, 'orders:' || case_id AS source, 'parsed' AS method FROM case_dx
UNION ALL SELECT 'dx:' || dx_id, 'dx', 'supplier:' || dx_id, 'code' FROM dx_node
UNION ALL SELECT 'finding:' || finding_id, 'finding', 'part:' || finding_id, coalesce(CASE lo WHEN 0 THEN 'exact' WHEN 1 THEN 'normalized' WHEN 2 THEN 'fuzzy' WHEN 3 THEN 'none' END, 'unseen') FROM finding_node LEFT JOIN (SELECT finding_id, min(CASE method WHEN 'exact' THEN 0 WHEN 'normalized' THEN 1 WHEN 'fuzzy' THEN 2 ELSE 3 END) AS lo FROM ({MENTION}) GROUP BY 1) USING (finding_id)
UNION ALL SELECT 'card:' || doc_id, 'card', 'documents:' || doc_id, 'parsed' FROM documents"""
EDGES = f"""SELECT 'case:' || case_id AS src, 'dx:' || dx_id AS dst, role AS etype, CASE role WHEN 'primary' THEN 3 WHEN 'secondary' THEN 2 ELSE 1 END::BIGINT AS weight, 'orders:' || case_id AS source, 'extracted' AS method FROM case_dx
UNION ALL SELECT 'case:' || case_id, 'finding:' || finding_id, 'r' || relevance, relevance, 'orders:' || case_id, method FROM case_finding JOIN ({MENTION}) USING (case_id, finding_id)
UNION ALL SELECT 'dx:' || dx_id, 'finding:' || finding_id, etype, n_cases, 'supplier:' || dx_id, 'typed' FROM dx_finding
UNION ALL SELECT 'dx:' || a, 'dx:' || b, 'related', 1, 'supplier:' || a, method FROM dx_links
UNION ALL SELECT 'card:' || doc_id, 'finding:' || finding_id, 'mentions', 1, 'documents:' || doc_id, 'token' FROM ({CARD})"""
d("q_graph_nodes", nodes, NODES)
d("q_graph_edges", edges, EDGES)
d("q_graph_stats", lambda t: edges(t).groupBy("etype", "method").agg(F.count("*").alias("n"), F.count_distinct("src").alias("sources")), f"SELECT etype, method, count(*) AS n, count(DISTINCT src) AS sources FROM ({EDGES}) GROUP BY 1, 2")
d("q_graph_degree", lambda t: edges(t).groupBy("src").count().groupBy(F.col("count").alias("degree")).agg(F.count("*").alias("n")), f"SELECT degree, count(*) AS n FROM (SELECT src, count(*) AS degree FROM ({EDGES}) GROUP BY 1) GROUP BY 1")
d("q_dx_finding_typed", lambda t: t.dx_finding.where("n_cases >= 2"), "SELECT * FROM dx_finding WHERE n_cases >= 2")
d("q_card_links", card_links, CARD)
d("q_segment_lines", lambda t: t.documents.select("doc_id", F.posexplode(F.split("text", "\n")).alias("ord", "line")).select("doc_id", "ord", F.length("line").alias("n")), "SELECT doc_id, CAST(i - 1 AS INT) AS ord, length(parts[i]) AS n FROM (SELECT doc_id, parts, unnest(range(1, len(parts) + 1)) AS i FROM (SELECT doc_id, string_split(text, chr(10)) AS parts FROM documents))")
d("q_segment_lossless", lambda t: t.documents.select("doc_id", F.posexplode(F.split("text", "\n")).alias("ord", "line")).groupBy("doc_id").agg(F.md5(F.array_join(F.transform(F.array_sort(F.collect_list(F.struct("ord", "line"))), lambda x: x["line"]), "\n")).alias("joined")), "SELECT doc_id, md5(text) AS joined FROM documents")


def gaps(t):
    """Rows without the source they point at, for every kind of element."""
    case, dx, finding = t.orders.select(F.col("o_orderkey").alias("case_id")), t.supplier.select(F.col("s_suppkey").alias("dx_id")), t.part.select(F.col("p_partkey").alias("finding_id"))
    g = Labels(t)
    checks = {
        "case_dx": (t.case_dx, case, "case_id"), "case_dx_node": (t.case_dx, dx, "dx_id"), "case_finding": (t.case_finding, case, "case_id"), "case_finding_node": (t.case_finding, finding, "finding_id"),
        "dx_finding": (t.dx_finding, dx, "dx_id"), "section": (t.chart_section, case, "case_id"), "label_dx": (g.patient_dx, dx, "dx_id"), "label_finding": (g.key_finding, finding, "finding_id"),
        "label_patient": (g.patient_dx, t.customer.select(F.col("c_custkey").alias("patient_id")), "patient_id"), "card": (t.documents.select(F.col("doc_id").alias("card")), t.documents.select(F.col("doc_id").alias("card")), "card"),
    }
    out = None
    for name, (rows, source, key) in checks.items():
        lost = rows.select(key).join(source, key, "left_anti").agg(F.count("*").alias("gaps"))
        n = rows.agg(F.count("*").alias("n")).select(F.lit(name).alias("checked"), "n").crossJoin(lost)
        out = n if out is None else out.unionByName(n)
    return out


_GAPS = {"case_dx": ("case_dx", "orders", "case_id = o_orderkey"), "case_dx_node": ("case_dx", "supplier", "dx_id = s_suppkey"), "case_finding": ("case_finding", "orders", "case_id = o_orderkey"), "case_finding_node": ("case_finding", "part", "finding_id = p_partkey"), "dx_finding": ("dx_finding", "supplier", "dx_id = s_suppkey"), "section": ("chart_section", "orders", "case_id = o_orderkey"), "label_dx": ("patient_dx", "supplier", "dx_id = s_suppkey"), "label_finding": ("key_finding", "part", "finding_id = p_partkey"), "label_patient": ("patient_dx", "customer", "patient_id = c_custkey"), "card": ("documents", "(SELECT doc_id AS d FROM documents)", "doc_id = d")}
d("q_provenance_gaps", gaps, " UNION ALL ".join(f"SELECT '{k}' AS checked, (SELECT count(*) FROM {v[0]}) AS n, (SELECT count(*) FROM {v[0]} ANTI JOIN {v[1]} ON {v[2]}) AS gaps" for k, v in _GAPS.items()))
d("q_provenance_walk", lambda t: Labels(t).patient_dx.select("patient_id", "dx_id").join(t.src_case.select("case_id", F.col("subject_id").alias("patient_id")), "patient_id").join(t.case_dx.where("role = 'primary'").select("case_id", "dx_id"), ["case_id", "dx_id"]).join(F.broadcast(t.dx_node.select("dx_id", "code")), "dx_id").select("patient_id", node("dx", "dx_id").alias("label"), "code", node("orders", "case_id").alias("source")), "SELECT patient_id, 'dx:' || dx_id AS label, code, 'orders:' || case_id AS source FROM patient_dx JOIN (SELECT case_id, subject_id AS patient_id FROM src_case) USING (patient_id) JOIN (SELECT case_id, dx_id FROM case_dx WHERE role = 'primary') USING (case_id, dx_id) JOIN dx_node USING (dx_id)")

# dx-dx links: pairs a < b.
d("q_link_ontology", lambda t: links.self_pairs(t.dx_node, "category"), "SELECT a, b FROM link_ontology")
d("q_link_site", lambda t: links.self_pairs(links.dx_site(t), "site"), "SELECT a, b FROM link_site")
d("q_link_shared", lambda t: links.shared(t).where("shared >= 140"), "SELECT a, b, shared FROM dx_shared WHERE shared >= 140")
d("q_link_curated", links.curated, "SELECT a, b FROM link_curated")
d("q_dx_links", links.every, "SELECT a, b, method FROM dx_links")
REF = "SELECT a.dx_id AS a, b.dx_id AS b, CASE (a.dx_id + b.dx_id) % 3 WHEN 0 THEN 'definitional' WHEN 1 THEN 'associative' ELSE 'shared' END AS expected FROM dx_node a JOIN dx_node b ON a.dx_id < b.dx_id WHERE (a.dx_id*7 + b.dx_id*11) % 41 = 3"
ref = links.reference
d("q_rel_reference", ref, REF)
d("q_rel_recall", lambda t: ref(t).join(links.every(t), ["a", "b"], "left").groupBy("expected", F.coalesce("method", F.lit("missed")).alias("method")).agg(F.count("*").alias("n")), f"SELECT expected, coalesce(method, 'missed') AS method, count(*) AS n FROM ({REF}) LEFT JOIN dx_links USING (a, b) GROUP BY 1, 2")
d("q_rel_gaps", lambda t: ref(t).join(links.every(t), ["a", "b"], "left_anti").join(links.shared(t), ["a", "b"], "left").groupBy(F.when(F.col("shared").isNull(), "disjoint").otherwise("below threshold").alias("reason")).agg(F.count("*").alias("n")), f"SELECT CASE WHEN shared IS NULL THEN 'disjoint' ELSE 'below threshold' END AS reason, count(*) AS n FROM ({REF}) ANTI JOIN dx_links USING (a, b) LEFT JOIN dx_shared USING (a, b) GROUP BY 1")
d("q_unlisted_links", lambda t: links.every(t).join(ref(t), ["a", "b"], "left_anti").agg(F.count("*").alias("n")), f"SELECT count(*) AS n FROM dx_links ANTI JOIN ({REF}) USING (a, b)")
d("q_threshold_sweep", lambda t: links.shared(t).withColumn("threshold", F.explode(F.array(*[F.lit(x) for x in (120, 130, 140, 150, 160)]))).where("shared >= threshold").groupBy("threshold").agg(F.count("*").alias("n")), "SELECT threshold, count(*) AS n FROM dx_shared, (VALUES (120), (130), (140), (150), (160)) AS x(threshold) WHERE shared >= threshold GROUP BY 1")

# Clustering.
d("q_compatible_pairs", lambda t: patients.compatible_pairs(t.src_case, t.case_dx), "WITH c AS (SELECT case_id, sex, age_years, CASE WHEN age_years < 40 THEN 'young' WHEN age_years < 65 THEN 'middle' ELSE 'older' END AS bucket, dx_id FROM src_case JOIN case_dx USING (case_id) WHERE role <> 'differential') SELECT a.case_id AS x, b.case_id AS y, count(*) AS shared FROM c a JOIN c b ON a.sex = b.sex AND a.bucket = b.bucket AND a.dx_id = b.dx_id AND a.case_id < b.case_id AND abs(a.age_years - b.age_years) <= 7 GROUP BY 1, 2")
d("q_case_edges", lambda t: patients.case_edges(t.src_case, t.case_dx))
d("q_cluster_invariants", lambda t: patients.invariants(patients.cluster(t.src_case, t.case_dx), t.src_case), "SELECT 0::BIGINT AS reused, 0::BIGINT AS mixed_sex, 0::BIGINT AS too_wide, 0::BIGINT AS too_large")
d("q_cluster", lambda t: patients.cluster(t.src_case, t.case_dx))
d("q_cluster_sizes", lambda t: patients.cluster(t.src_case, t.case_dx).groupBy("patient_id").agg(F.count("*").alias("cases")).groupBy("cases").agg(F.count("*").alias("patients")))
d("q_cluster_exact", lambda t: patients.cluster_exact(t.src_case, t.case_dx))

# Timelines of given patients.
PE = "(SELECT subject_id AS patient_id, case_id, recorded_at, CAST(row_number() OVER (PARTITION BY subject_id ORDER BY recorded_at, case_id) AS BIGINT) AS seq, year(recorded_at)*12 + month(recorded_at) AS ym FROM src_case)"


def encounters(t):
    w = Window.partitionBy("patient_id").orderBy("recorded_at", "case_id")
    return t.src_case.select(F.col("subject_id").alias("patient_id"), "case_id", "recorded_at").withColumns({"seq": F.row_number().over(w).cast("long"), "ym": F.year("recorded_at") * 12 + F.month("recorded_at")})


d("q_timeline", lambda t: encounters(t).withColumn("month", F.col("ym") - F.min("ym").over(Window.partitionBy("patient_id"))).select("patient_id", "case_id", "seq", "month"), f"SELECT patient_id, case_id, seq, ym - min(ym) OVER (PARTITION BY patient_id) AS month FROM {PE}")


def carry(t, rows, item):
    """Items first seen before an encounter: the first occurrence joined to later encounters, not a growing list."""
    e = encounters(t)
    first = e.join(rows, "case_id").groupBy("patient_id", item).agg(F.min("seq").alias("first"))
    return e.join(first, "patient_id").where("first < seq").groupBy("patient_id", "seq").agg(F.count("*").alias("n"))


CARRY = "SELECT patient_id, seq, count(*) AS n FROM {pe} e JOIN (SELECT patient_id, {item}, min(seq) AS first FROM {pe} JOIN {rows} USING (case_id) GROUP BY 1, 2) USING (patient_id) WHERE first < seq GROUP BY 1, 2"
d("q_problem_carry", lambda t: carry(t, t.case_dx, "dx_id"), CARRY.format(pe=PE, item="dx_id", rows="case_dx"))
d("q_med_carry", lambda t: carry(t, t.case_finding.join(t.finding_node.where("kind = 'medication'").select("finding_id"), "finding_id"), "finding_id"), CARRY.format(pe=PE, item="finding_id", rows="(SELECT * FROM case_finding JOIN finding_node USING (finding_id) WHERE kind = 'medication')"))
d("q_profile", lambda t: t.src_case.join(t.case_dx, "case_id").groupBy(F.col("subject_id").alias("patient_id"), "dx_id").agg(F.count("*").alias("n")).where("n >= 2"), "SELECT subject_id AS patient_id, dx_id, count(*) AS n FROM src_case JOIN case_dx USING (case_id) GROUP BY 1, 2 HAVING count(*) >= 2")
d("q_hpi_continuity", lambda t: encounters(t).withColumn("prev", F.lag("case_id").over(Window.partitionBy("patient_id").orderBy("seq"))).select("case_id", F.when(F.col("prev").isNull(), "first visit").otherwise(F.concat(F.lit("seen before at "), F.col("prev").cast("string"))).alias("history")), f"SELECT case_id, CASE WHEN prev IS NULL THEN 'first visit' ELSE 'seen before at ' || prev END AS history FROM (SELECT case_id, lag(case_id) OVER (PARTITION BY patient_id ORDER BY seq) AS prev FROM {PE})")
d("q_validate_records", lambda t: t.src_case.groupBy("subject_id").agg(F.count_distinct("sex").alias("sexes"), F.min("age_years").alias("low"), F.max("age_years").alias("high")).agg(F.sum((F.col("sexes") > 1).cast("long")).alias("mixed_sex"), F.sum((F.col("low") < 18).cast("long")).alias("too_young")), "SELECT sum(CASE WHEN sexes > 1 THEN 1 ELSE 0 END)::BIGINT AS mixed_sex, sum(CASE WHEN low < 18 THEN 1 ELSE 0 END)::BIGINT AS too_young FROM (SELECT subject_id, count(DISTINCT sex) AS sexes, min(age_years) AS low FROM src_case GROUP BY 1)")

# Tasks, splits and rewards.
CASES = "(SELECT subject_id AS patient_id, array_to_string(list_sort(list(case_id)), ',') AS encounters FROM src_case GROUP BY 1)"
INST = f"""SELECT 'diagnosis' AS task, 'diagnosis:' || patient_id AS instance_id, patient_id, encounters, n_gold FROM (SELECT patient_id, count(*) AS n_gold FROM patient_dx GROUP BY 1) JOIN {CASES} USING (patient_id)
UNION ALL SELECT 'summarization', 'summarization:' || patient_id, patient_id, encounters, n_gold FROM (SELECT patient_id, count(*) AS n_gold FROM key_finding GROUP BY 1) JOIN {CASES} USING (patient_id)
UNION ALL SELECT 'retrieval', 'retrieval:' || patient_id, patient_id, encounters, n_gold FROM (SELECT patient_id, count(*) FILTER (WHERE grade >= 2) AS n_gold FROM section_grade GROUP BY 1) JOIN {CASES} USING (patient_id)
UNION ALL SELECT 'specialty', 'specialty:' || patient_id || ':' || specialty, patient_id, encounters, coalesce(n, 0) AS n_gold FROM spec_item LEFT JOIN (SELECT patient_id, specialty, count(*) AS n FROM spec_gold GROUP BY 1, 2) USING (patient_id, specialty) JOIN {CASES} USING (patient_id)
UNION ALL SELECT 'imaging', 'imaging:' || instance_id, subject_id, CAST(instance_id AS VARCHAR), n_gold FROM (SELECT instance_id, count(*) AS n_gold FROM imaging_gold GROUP BY 1) JOIN src_case ON instance_id = case_id"""


with_split = lambda t: instances.of(t, named=True)
INST_S = f"SELECT * FROM ({INST}) JOIN (SELECT patient_id, split FROM split_of) USING (patient_id)"
d("q_instances", with_split, INST_S)
d("q_difficulty", lambda t: splits.difficulty(splits.profile(t)).select("patient_id", "load", "tertile"), "SELECT patient_id, load, tertile FROM pat_level")
d("q_dominant_chapter", lambda t: splits.profile(t).select("patient_id", "chapter"), "SELECT patient_id, chapter FROM pat_profile")
d("q_split_assign", splits.assign, "SELECT patient_id, chapter, band, tertile, split FROM split_of")
d("q_split_counts", lambda t: splits.assign(t).groupBy("split").agg(F.count("*").alias("n")), "SELECT split, count(*) AS n FROM split_of GROUP BY 1")


def balance(t):
    """For each stratum of chapter and encounters, its share of the training and of the held-out patients."""
    rows = splits.assign(t).where("split <> 'public'")
    n = rows.groupBy("split").agg(F.count("*").alias("n"))
    cell = rows.groupBy("chapter", "band", "split").agg(F.count("*").alias("c")).join(F.broadcast(n), "split").withColumn("share", F.col("c") / F.col("n"))
    wide = cell.groupBy("chapter", "band").pivot("split", ["training", "heldout"]).agg(F.first("share")).fillna(0.0)
    return wide.select("chapter", "band", F.round("training", 6).alias("training"), F.round("heldout", 6).alias("heldout"))


BALANCE = "SELECT chapter, band, round(coalesce(sum(share) FILTER (WHERE split = 'training'), 0), 6) AS training, round(coalesce(sum(share) FILTER (WHERE split = 'heldout'), 0), 6) AS heldout FROM (SELECT chapter, band, split, count(*) / sum(count(*)) OVER (PARTITION BY split) AS share FROM split_of WHERE split <> 'public' GROUP BY 1, 2, 3) GROUP BY 1, 2"
d("q_split_balance", balance, BALANCE)
d("q_split_leaks", lambda t: t.src_case.join(splits.assign(t), F.col("subject_id") == F.col("patient_id")).groupBy("case_id").agg(F.count_distinct("split").alias("splits")).groupBy("splits").agg(F.count("*").alias("cases")), "SELECT splits, count(*) AS cases FROM (SELECT case_id, count(DISTINCT split) AS splits FROM src_case JOIN split_of ON subject_id = patient_id GROUP BY 1) GROUP BY 1")


def split_random(t):
    """The unstratified baseline: patients by hash alone."""
    rows = splits.chosen(t.customer.select(F.col("c_custkey").alias("patient_id"), F.lit("all").alias("of")), ["of"], splits.PUBLIC / splits.ALL).withColumnRenamed("chosen", "_p")
    rows = splits.chosen(rows, ["of"], (splits.PUBLIC + splits.HELD) / splits.ALL)
    return rows.select("patient_id", F.when(F.col("_p"), "public").when(F.col("chosen"), "heldout").otherwise("training").alias("split"))


d("q_split_random", split_random, "SELECT patient_id, CASE WHEN r <= round(n * (200 / 1268.0::DOUBLE)) THEN 'public' WHEN r <= round(n * (468 / 1268.0::DOUBLE)) THEN 'heldout' ELSE 'training' END AS split FROM (SELECT c_custkey AS patient_id, count(*) OVER () AS n, row_number() OVER (ORDER BY (c_custkey*7919) % 10007, c_custkey) AS r FROM customer)")


def split_rows(t):
    """The row-level baseline, which leaks: cases are split by their own hash, so patients stand in several splits."""
    of = F.when((F.col("case_id") * 7919) % 1268 < 200, "public").when((F.col("case_id") * 7919) % 1268 < 468, "heldout").otherwise("training")
    return t.src_case.select("subject_id", of.alias("split")).groupBy("subject_id").agg(F.count_distinct("split").alias("splits")).groupBy("splits").agg(F.count("*").alias("patients"))


d("q_split_rows", split_rows, "SELECT splits, count(*) AS patients FROM (SELECT subject_id, count(DISTINCT CASE WHEN (case_id*7919) % 1268 < 200 THEN 'public' WHEN (case_id*7919) % 1268 < 468 THEN 'heldout' ELSE 'training' END) AS splits FROM src_case GROUP BY 1) GROUP BY 1")
DXS = "SELECT DISTINCT split, dx_id FROM split_of JOIN patient_dx USING (patient_id)"
d("q_dx_novelty", lambda t: (lambda r: r.where("split = 'heldout'").select("dx_id").join(r.where("split = 'training'").select("dx_id", F.lit(1).alias("seen")), "dx_id", "left").groupBy(F.coalesce("seen", F.lit(0)).alias("seen")).agg(F.count("*").alias("n")))(splits.assign(t).join(Labels(t).patient_dx, "patient_id").select("split", "dx_id").distinct()), f"SELECT CASE WHEN dx_id IN (SELECT dx_id FROM ({DXS}) WHERE split = 'training') THEN 1 ELSE 0 END AS seen, count(*) AS n FROM ({DXS}) WHERE split = 'heldout' GROUP BY 1")
d("q_instance_counts", lambda t: with_split(t).groupBy("task", "split").agg(F.count("*").alias("n")), f"SELECT task, split, count(*) AS n FROM ({INST_S}) GROUP BY 1, 2")
# Of the held-out split only the questions are given out; its gold is read by the scorer alone, which returns one mean for each system.


def scorer(t):
    g = Labels(t, "heldout")
    p = Panel(g)
    return S.macro(S.severity_f1(p.dx, g.patient_dx, neutral=g.documented, systems=p.systems))


def rollouts(t, k=4):
    """Each training instance and rollout with its reward; rollout r is answered by policy r of the simulated panel, silence is rewarded 0."""
    g = Labels(t, "training")
    p = Panel(g, k)
    scored = {
        "diagnosis": S.severity_f1(p.dx, g.patient_dx, neutral=g.documented, systems=p.systems).select("m", "value"), "summarization": S.set_prf(p.finding, g.key_finding, keys=["patient_id"], item="finding_id", systems=p.systems).select("m", "value"),
        "specialty": S.set_prf(p.specialty, g.spec_gold, keys=["patient_id", "specialty"], item="finding_id", instances=g.spec_item, systems=p.systems).select("m", "value"),
        "retrieval": S.precision_at(p.ranked, g.section_grade, systems=p.systems).select("m", "value"), "imaging": S.set_prf(p.imaging, g.imaging_gold, keys=["instance_id"], item="concept", systems=p.systems).select("m", "value"),
    }
    out = None
    for task, f in scored.items():
        f = f.groupBy(F.lit(task).alias("task"), F.col("m").alias("rollout")).agg(F.count("*").alias("n"), F.round(F.avg("value"), 6).alias("reward"), F.count_if((F.col("value") < 0) | (F.col("value") > 1)).alias("outside"))
        out = f if out is None else out.unionByName(f)
    return out
