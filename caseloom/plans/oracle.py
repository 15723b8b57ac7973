"""The adapter views in DuckDB's SQL, for oracles: ``sql("SELECT ...")`` puts the needed ones before a query."""

from __future__ import annotations

import re

SEV = "CASE acuity WHEN '1-URGENT' THEN 3 WHEN '2-HIGH' THEN 3 WHEN '3-MEDIUM' THEN 2 WHEN '4-NOT SPECIFIED' THEN 2 ELSE 1 END"
REL = "CASE l_returnflag WHEN 'R' THEN 3 WHEN 'A' THEN 2 ELSE 1 END"
VIEWS = {
    "src_case": "SELECT o_orderkey AS case_id, o_custkey AS subject_id, o_orderdate AS recorded_at, 18 + (o_orderkey*7 + o_custkey*3) % 72 AS age_years, CASE WHEN o_custkey % 2 = 0 THEN 'F' ELSE 'M' END AS sex, c_mktsegment AS setting, o_orderpriority AS acuity FROM orders JOIN customer ON o_custkey = c_custkey",
    "dx_node": "SELECT s_suppkey AS dx_id, substr(r_name,1,2) || lpad(CAST(n_nationkey AS VARCHAR),2,'0') || '.' || lpad(CAST(s_suppkey AS VARCHAR),6,'0') AS code, n_name AS category, r_name AS chapter FROM supplier JOIN nation ON s_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey",
    "case_dx": "SELECT case_id, dx_id, CASE WHEN row_number() OVER (PARTITION BY case_id ORDER BY top DESC, dx_id) = 1 THEN 'primary' WHEN final = 1 THEN 'secondary' ELSE 'differential' END AS role FROM (SELECT l_orderkey AS case_id, l_suppkey AS dx_id, max(l_extendedprice) AS top, max(CASE WHEN l_linestatus = 'F' THEN 1 ELSE 0 END) AS final FROM lineitem GROUP BY ALL)",
    "finding_node": "SELECT p_partkey AS finding_id, p_name AS term, CASE split_part(p_type,' ',1) WHEN 'STANDARD' THEN 'symptom' WHEN 'ECONOMY' THEN 'sign' WHEN 'MEDIUM' THEN 'lab' WHEN 'PROMO' THEN 'imaging' WHEN 'SMALL' THEN 'medication' WHEN 'LARGE' THEN 'history' ELSE 'other' END AS kind, p_brand AS site FROM part",
    "case_finding": f"SELECT l_orderkey AS case_id, l_partkey AS finding_id, max({REL}) AS relevance FROM lineitem GROUP BY ALL",
    "dx_finding": f"SELECT *, CASE grade WHEN 3 THEN 'causes' WHEN 2 THEN 'suggests' ELSE 'coexists' END AS etype FROM (SELECT l_suppkey AS dx_id, l_partkey AS finding_id, count(DISTINCT l_orderkey) AS n_cases, max({REL}) AS grade FROM lineitem GROUP BY ALL)",
    "chart_section": "SELECT case_id*10 + ord AS section_id, case_id, ord, kind AS stype, array_to_string(list_sort(list(DISTINCT term)), '; ') AS body FROM (SELECT case_id, kind, term, CASE kind WHEN 'symptom' THEN 1 WHEN 'sign' THEN 2 WHEN 'lab' THEN 3 WHEN 'imaging' THEN 4 WHEN 'medication' THEN 5 WHEN 'history' THEN 6 ELSE 7 END AS ord FROM case_finding JOIN finding_node USING (finding_id)) GROUP BY case_id, kind, ord",
    "raw_mention": "SELECT l_orderkey AS case_id, l_partkey AS finding_id, CASE (l_orderkey + l_partkey) % 5 WHEN 0 THEN p_name WHEN 1 THEN '  ' || upper(p_name) || ' ' WHEN 2 THEN array_to_string(list_reverse(string_split(p_name,' ')), ' ') WHEN 3 THEN substr(p_name, 1, length(p_name) - 1) ELSE 'zz' || CAST(l_partkey AS VARCHAR) END AS surface, p_name AS true_term FROM (SELECT DISTINCT l_orderkey, l_partkey FROM lineitem) JOIN part ON l_partkey = p_partkey",
    "patient_dx": f"SELECT subject_id AS patient_id, dx_id, max({SEV}) AS weight, min(acuity) AS acuity FROM src_case JOIN case_dx USING (case_id) WHERE role = 'primary' GROUP BY ALL",
    "documented": "SELECT DISTINCT subject_id AS patient_id, dx_id FROM src_case JOIN case_dx USING (case_id)",
    "systems": "SELECT * FROM (VALUES (1,32,12),(2,30,11),(3,27,10),(4,38,14),(5,34,18),(6,34,15),(7,35,16),(8,32,20),(9,46,24),(10,71,30)) AS t(m, drops, noise)",
    "pred_dx": "SELECT m, patient_id, dx_id FROM patient_dx, systems WHERE (dx_id*31 + patient_id*17 + m*13) % 100 >= drops UNION ALL SELECT m, d.patient_id, d.dx_id FROM documented d ANTI JOIN patient_dx g USING (patient_id, dx_id) CROSS JOIN systems WHERE (d.dx_id*29 + d.patient_id*19 + m*7) % 100 < noise UNION ALL SELECT m, patient_id, dx_id FROM (SELECT DISTINCT m, noise, p.patient_id, 1 + (p.patient_id*7 + m*5 + k*13) % n.n AS dx_id FROM (SELECT DISTINCT patient_id FROM patient_dx) p, systems, (VALUES (0),(1),(2)) AS ks(k), (SELECT count(*) AS n FROM supplier) n) x ANTI JOIN documented USING (patient_id, dx_id) WHERE (dx_id*29 + patient_id*19 + m*7) % 100 < noise * 2",
    "key_finding": "SELECT DISTINCT subject_id AS patient_id, finding_id FROM src_case JOIN case_finding USING (case_id) WHERE relevance = 3",
    "chart_finding": "SELECT subject_id AS patient_id, finding_id, max(relevance) AS relevance FROM src_case JOIN case_finding USING (case_id) GROUP BY ALL",
    "pred_finding": "SELECT m, patient_id, finding_id FROM chart_finding, systems WHERE (relevance = 3 AND (finding_id*31 + patient_id*17 + m*13) % 100 >= drops + 15) OR (relevance < 3 AND (finding_id*29 + patient_id*19 + m*7) % 100 < noise * 2)",
    "query_dx": "SELECT patient_id, dx_id FROM (SELECT *, row_number() OVER (PARTITION BY patient_id ORDER BY weight DESC, dx_id) AS rn FROM patient_dx) WHERE rn = 1",
    "section_grade": "SELECT patient_id, section_id, max(CASE WHEN grade IS NULL THEN 0 WHEN relevance = 3 AND grade = 3 THEN 3 WHEN relevance >= 2 THEN 2 ELSE 1 END) AS grade FROM (SELECT q.patient_id, c.case_id*10 + CASE f.kind WHEN 'symptom' THEN 1 WHEN 'sign' THEN 2 WHEN 'lab' THEN 3 WHEN 'imaging' THEN 4 WHEN 'medication' THEN 5 WHEN 'history' THEN 6 ELSE 7 END AS section_id, cf.relevance, e.grade FROM query_dx q JOIN src_case c ON c.subject_id = q.patient_id JOIN case_finding cf USING (case_id) JOIN finding_node f USING (finding_id) LEFT JOIN dx_finding e ON e.dx_id = q.dx_id AND e.finding_id = cf.finding_id) GROUP BY ALL",
    "ranked": "SELECT m, patient_id, section_id, row_number() OVER (PARTITION BY m, patient_id ORDER BY est DESC, tie, section_id) AS rank FROM (SELECT m, patient_id, section_id, CASE WHEN (section_id*31 + patient_id*17 + m*13) % 100 >= drops THEN grade ELSE (section_id + m) % 4 END AS est, (section_id*37 + patient_id*11 + m*3) % 101 AS tie FROM section_grade, systems)",
    "imaging_gold": "SELECT DISTINCT case_id AS instance_id, finding_id AS concept FROM case_finding JOIN finding_node USING (finding_id) WHERE kind = 'imaging' AND case_id IN (SELECT case_id FROM src_case) UNION SELECT case_id AS instance_id, 1000000000 + dx_id AS concept FROM case_dx WHERE role = 'primary' AND case_id IN (SELECT case_id FROM src_case) AND case_id IN (SELECT case_id FROM case_finding JOIN finding_node USING (finding_id) WHERE kind = 'imaging')",
    "pred_imaging": "SELECT m, instance_id, concept FROM imaging_gold, systems WHERE (concept*31 + instance_id*17 + m*13) % 100 >= drops + 12 UNION ALL SELECT DISTINCT m, case_id AS instance_id, finding_id AS concept FROM case_finding JOIN finding_node USING (finding_id) CROSS JOIN systems WHERE kind <> 'imaging' AND case_id IN (SELECT instance_id FROM imaging_gold) AND (finding_id*29 + case_id*19 + m*7) % 100 < noise",
    "link_ontology": "SELECT a.dx_id AS a, b.dx_id AS b FROM dx_node a JOIN dx_node b ON a.category = b.category AND a.dx_id < b.dx_id",
    "link_site": "SELECT a.dx_id AS a, b.dx_id AS b FROM dx_site a JOIN dx_site b ON a.site = b.site AND a.dx_id < b.dx_id",
    "dx_shared": "SELECT a.dx_id AS a, b.dx_id AS b, count(*) AS shared FROM dx_finding a JOIN dx_finding b ON a.finding_id = b.finding_id AND a.dx_id < b.dx_id GROUP BY 1, 2",
    "link_curated": "SELECT dx_id AS a, dx_id + 1 AS b FROM dx_node WHERE dx_id % 20 = 1 AND dx_id + 1 IN (SELECT dx_id FROM dx_node)",
    "dx_links": "SELECT a, b, CASE min(k) WHEN 0 THEN 'ontology' WHEN 1 THEN 'site' WHEN 2 THEN 'shared' ELSE 'curated' END AS method FROM (SELECT a, b, 0 AS k FROM link_ontology UNION ALL SELECT a, b, 1 FROM link_site UNION ALL SELECT a, b, 2 FROM dx_shared WHERE shared >= 140 UNION ALL SELECT a, b, 3 FROM link_curated) GROUP BY 1, 2",
    "case_own": "SELECT DISTINCT subject_id AS patient_id, case_id, dx_id FROM src_case JOIN case_dx USING (case_id) WHERE role <> 'differential'",
    "dx_owned": "SELECT DISTINCT patient_id, dx_id, finding_id FROM case_own JOIN case_finding USING (case_id) JOIN dx_finding USING (dx_id, finding_id)",
    "dx_hop": "SELECT a AS head, b AS dx_id FROM dx_links UNION ALL SELECT b, a FROM dx_links UNION ALL SELECT dx_id, dx_id FROM dx_node",
    "spec_gold": "SELECT DISTINCT p.patient_id, n.category AS specialty, o.finding_id FROM (SELECT DISTINCT patient_id, dx_id FROM case_own) p JOIN dx_node n USING (dx_id) JOIN dx_hop h ON h.head = p.dx_id JOIN dx_owned o ON o.patient_id = p.patient_id AND o.dx_id = h.dx_id",
    "spec_item": "SELECT patient_id, specialty, FALSE AS absent FROM (SELECT DISTINCT patient_id, specialty FROM spec_gold) UNION ALL SELECT patient_id, specialty, TRUE AS absent FROM (SELECT p.patient_id, n_name AS specialty, row_number() OVER (PARTITION BY p.patient_id ORDER BY (p.patient_id*13 + n_nationkey*7) % 25, n_nationkey) AS rn FROM (SELECT DISTINCT patient_id FROM spec_gold) p CROSS JOIN nation WHERE NOT EXISTS (SELECT 1 FROM spec_gold g WHERE g.patient_id = p.patient_id AND g.specialty = n_name)) WHERE rn <= 2",
    "pred_spec": "SELECT m, patient_id, specialty, finding_id FROM spec_gold, systems WHERE (finding_id*31 + patient_id*17 + m*13) % 100 >= drops + 5 UNION ALL SELECT m, patient_id, specialty, 1 + (patient_id*3 + m) % 7 AS finding_id FROM spec_item, systems WHERE absent AND (patient_id*29 + m*7 + length(specialty)) % 100 < noise * 2",
    "pat_profile": "SELECT patient_id, n_cases, n_cases*3 + d AS load, CASE WHEN n_cases <= 5 THEN 1 WHEN n_cases <= 10 THEN 2 WHEN n_cases <= 15 THEN 3 ELSE 4 END AS band, chapter FROM (SELECT subject_id AS patient_id, count(DISTINCT case_id) AS n_cases, count(DISTINCT dx_id) AS d FROM all_case JOIN case_dx USING (case_id) GROUP BY 1) JOIN (SELECT subject_id AS patient_id, chapter FROM all_case JOIN case_dx USING (case_id) JOIN dx_node USING (dx_id) GROUP BY 1, 2 QUALIFY row_number() OVER (PARTITION BY subject_id ORDER BY count(*) DESC, chapter) = 1) USING (patient_id)",
    "pat_level": "SELECT *, CASE WHEN load <= (SELECT quantile_cont(load, 1/3) FROM pat_profile) THEN 1 WHEN load <= (SELECT quantile_cont(load, 2/3) FROM pat_profile) THEN 2 ELSE 3 END AS tertile FROM pat_profile",
    "pub_quota": "SELECT tertile, band, f + CASE WHEN row_number() OVER (ORDER BY round(q - f, 9) DESC, tertile, band) <= round(sum(q) OVER ()) - sum(f) OVER () THEN 1 ELSE 0 END AS take FROM (SELECT *, floor(q) AS f FROM (SELECT tertile, band, count(*) * (200 / 1268.0::DOUBLE) AS q FROM pat_level GROUP BY 1, 2))",
    "pub_flag": "SELECT p.*, row_number() OVER (PARTITION BY tertile, band ORDER BY (patient_id*7919) % 10007, patient_id) <= take AS pub FROM pat_level p JOIN pub_quota USING (tertile, band)",
    "held_quota": "SELECT chapter, band, f + CASE WHEN row_number() OVER (ORDER BY round(q - f, 9) DESC, chapter, band) <= round(sum(q) OVER ()) - sum(f) OVER () THEN 1 ELSE 0 END AS take FROM (SELECT *, floor(q) AS f FROM (SELECT chapter, band, count(*) * (268 / 1068.0::DOUBLE) AS q FROM pub_flag WHERE NOT pub GROUP BY 1, 2))",
    "split_of": "SELECT patient_id, chapter, band, tertile, 'public' AS split FROM pub_flag WHERE pub UNION ALL SELECT patient_id, chapter, band, tertile, CASE WHEN row_number() OVER (PARTITION BY chapter, band ORDER BY (patient_id*7919) % 10007, patient_id) <= take THEN 'heldout' ELSE 'training' END FROM pub_flag JOIN held_quota USING (chapter, band) WHERE NOT pub",
    "dx_site": "SELECT dx_id, site FROM (SELECT dx_id, site, row_number() OVER (PARTITION BY dx_id ORDER BY sum(n_cases) DESC, site) AS rn FROM dx_finding JOIN finding_node USING (finding_id) GROUP BY dx_id, site) WHERE rn = 1",
}


VIEWS["all_case"] = VIEWS["src_case"]


def sql(query: str, split: str | None = None) -> str:
    """The query with the views that it uses, directly or not, as common table expressions before it.

    With ``split``, ``src_case`` holds the cases of this split's patients; ``all_case`` holds all.
    """
    views = dict(VIEWS)
    if split:
        views["src_case"] = f"SELECT * FROM all_case WHERE subject_id IN (SELECT patient_id FROM split_of WHERE split = '{split}')"
    names = list(views)
    need: set[str] = set()

    def add(text: str) -> None:
        for n in names:
            if n not in need and re.search(rf"\b{n}\b", text):
                need.add(n)
                add(views[n])

    add(query)
    ordered: list[str] = []

    def place(n: str) -> None:
        for k in names:
            if k != n and k in need and k not in ordered and re.search(rf"\b{k}\b", views[n]):
                place(k)
        if n not in ordered:
            ordered.append(n)

    for n in names:
        if n in need:
            place(n)
    if not ordered:
        return query
    head = ", ".join(f"{n} AS ({views[n]})" for n in ordered)
    return f"WITH {head}, {query[5:]}" if query.startswith("WITH ") else f"WITH {head} {query}"
