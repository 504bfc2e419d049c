"""SQL for the registered queries, written from the tables' relations rather than from the plans."""

from __future__ import annotations

from .functions.lexicon import WORDS
from .operators.mapping import CLASSES
from .operators.measures import PUBLISHED, T95

CLASS_OF_CUSTOMER = "upper(substr(c_mktsegment, 1, 1)) || lower(substr(c_mktsegment, 2)) || 'Customer'"
CLASS_OF_PART = "upper(substr(p_type, 1, 1)) || lower(substr(p_type, 2)) || 'Part'"
CLASS_OF_ORDER = "CASE o_orderstatus WHEN 'F' THEN 'FinishedOrder' WHEN 'O' THEN 'OpenOrder' ELSE 'PendingOrder' END"
ITEM = "'lineitem/' || l_orderkey || '-' || l_linenumber || '-' || l_partkey || '-' || l_suppkey"

# (table, source, subject, class, links: predicate → target, texts: predicate → column, other literals)
STAR = [
    ("region", "geo", "'region/' || r_regionkey", "'Region'", {}, {"name": "r_name"}, []),
    ("nation", "geo", "'nation/' || n_nationkey", "'Nation'", {"region": "'region/' || n_regionkey"}, {"name": "n_name"}, []),
    ("customer", "sales", "'customer/' || c_custkey", CLASS_OF_CUSTOMER, {"nation": "'nation/' || c_nationkey"}, {"name": "c_name", "marketSegment": "c_mktsegment"}, ["accountBalance"]),
    ("orders", "sales", "'order/' || o_orderkey", CLASS_OF_ORDER, {"customer": "'customer/' || o_custkey"}, {"orderStatus": "o_orderstatus", "orderPriority": "o_orderpriority"}, ["totalPrice", "orderDate"]),
    ("lineitem", "sales", ITEM, "'LineItem'", {"order": "'order/' || l_orderkey", "part": "'part/' || l_partkey", "supplier": "'supplier/' || l_suppkey"}, {"returnFlag": "l_returnflag", "lineStatus": "l_linestatus"}, ["quantity", "extendedPrice", "discount", "tax", "shipDate"]),
    ("supplier", "catalog", "'supplier/' || s_suppkey", "'Supplier'", {"nation": "'nation/' || s_nationkey"}, {"name": "s_name"}, ["accountBalance"]),
    ("part", "catalog", "'part/' || p_partkey", CLASS_OF_PART, {}, {"name": "p_name", "brand": "p_brand", "partType": "p_type"}, ["size", "retailPrice"]),
]
PREDICATES = sorted({p for _, _, _, _, links, texts, rest in STAR for p in (*links, *texts, *rest)} | {"type"})

LINKS = " UNION ALL ".join(f"SELECT {s} AS s, '{p}' AS p, {o} AS o, {c} AS c, '{src}' AS source FROM {t}" for t, src, s, c, links, _, _ in STAR for p, o in [*links.items(), ("type", f"'class/' || {c}")])
TEXTS = " UNION ALL ".join(f"SELECT {s} AS s, '{p}' AS p, {o} AS o, {c} AS c, '{src}' AS source FROM {t}" for t, src, s, c, _, texts, _ in STAR for p, o in texts.items())
BASE = f"links AS ({LINKS}), texts AS ({TEXTS}), short AS (SELECT * FROM texts WHERE length(o) BETWEEN 1 AND 80)"
SCORES = f"{BASE}, carried AS (SELECT DISTINCT s AS e, o AS lit FROM short), pairs AS (SELECT DISTINCT s, o AS e FROM links), scores AS (SELECT lit, count(DISTINCT pairs.s) AS score FROM carried LEFT JOIN pairs USING (e) GROUP BY lit)"
PREDICATE_ROWS = ", ".join(f"('{p}')" for p in PREDICATES)
CACHE = f"""{SCORES}, top AS (SELECT * FROM scores ORDER BY score DESC, lit LIMIT 200), residual AS (SELECT lit, length(lit) AS lit_len, score FROM scores WHERE lit NOT IN (SELECT lit FROM top)),
terms AS (SELECT lit AS term, 'literal' AS kind, length(lit) AS term_len, score FROM top UNION ALL SELECT p, 'predicate', length(p), 0 FROM (VALUES {PREDICATE_ROWS}) v(p))"""


def closure_cte() -> str:
    rows = ", ".join(f"('{c}', {'NULL' if p is None else repr(p)})" for c, p in CLASSES.items())
    return f"h(c, parent) AS (VALUES {rows}), up(c, anc, depth) AS (SELECT c, c, 0 FROM h UNION ALL SELECT up.c, h.parent, depth + 1 FROM up JOIN h ON up.anc = h.c WHERE h.parent IS NOT NULL)"


HIERARCHY = "(VALUES " + ", ".join(f"('{c}', {'NULL' if p is None else repr(p)})" for c, p in CLASSES.items()) + ") h(c, parent)"


def complete(text: str, k: int = 10, gamma: int = 10, use_index: bool = True) -> str:
    hits = f"SELECT term, 0 AS tier, score, term_len, 'index' AS origin FROM terms WHERE contains(lower(term), '{text.lower()}') ORDER BY score DESC, term_len, term LIMIT {k if use_index else 0}"
    rest = f"SELECT lit, 1, 0, lit_len, 'bin' FROM residual WHERE contains(lower(lit), '{text.lower()}') AND lit_len BETWEEN {len(text)} AND {len(text) + gamma} ORDER BY lit_len, lit LIMIT {k}"
    return f"WITH {CACHE}, both_ AS (SELECT * FROM ({hits}) UNION ALL SELECT * FROM ({rest})), ranked AS (SELECT row_number() OVER (ORDER BY tier, score DESC, term_len, term) AS rank, term, origin FROM both_) SELECT * FROM ranked WHERE rank <= {k}"


def profile() -> str:
    parts = []
    for t, src, _, _, links, texts, rest in STAR:
        parts += [f"SELECT '{src}' AS source, '{p}' AS p, 'iri' AS o_kind, count(*) AS n FROM {t}" for p in ("type", *links)]
        parts += [f"SELECT '{src}', '{p}', 'literal', count(*) FROM {t}" for p in (*texts, *rest)]
    lines = "(SELECT unnest(list_distinct(string_split(text, chr(10)))) AS l FROM {t})"
    one = lambda src, p, kind, frm: f"SELECT '{src}', '{p}', '{kind}', count(*) FROM {frm}"
    parts += [one("text", p, k, "documents") for p, k in (("type", "iri"), ("origin", "iri"), ("characters", "literal"))]
    parts += [one("text", "line", "literal", lines.format(t="documents") + " WHERE l <> ''"), one("text", "passage", "literal", lines.format(t="benchmark") + " WHERE l <> ''")]
    parts += [one("text", "type", "iri", "(SELECT DISTINCT source FROM documents)"), one("text", "name", "literal", "(SELECT DISTINCT source FROM documents)"), one("text", "type", "iri", "benchmark")]
    parts += [one("text", "quality", "literal", "labels"), one("text", "toxic", "literal", "labels")]
    parts += [one("web", "type", "iri", "pages"), one("web", "host", "iri", "pages"), one("web", "url", "literal", "pages"), one("web", "title", "literal", "pages WHERE regexp_extract(html, '<title>([^<]*)</title>', 1) <> ''")]
    parts += [one("web", "linksTo", "iri", "(SELECT unnest(list_distinct(regexp_extract_all(html, 'href=\"(/[^\"]*)\"', 1))) FROM pages)")]
    parts += [one("talk", p, k, "conversations") for p, k in (("type", "iri"), ("conversation", "iri"), ("role", "literal"))]
    parts += [one("talk", "utterance", "literal", lines.format(t="conversations") + " WHERE l <> ''")]
    parts += [one("log", p, k, "events") for p, k in (("type", "iri"), ("user", "iri"), ("eventType", "literal"), ("value", "literal"), ("at", "literal"), ("k", "literal"))]
    parts += [one("vec", "type", "iri", "embeddings"), one("vec", "cluster", "literal", "embeddings")]
    return f"SELECT source, p, o_kind, CAST(sum(n) AS BIGINT) AS n FROM ({' UNION ALL '.join(parts)}) GROUP BY source, p, o_kind"


def stats() -> str:
    parts = []
    for t, src, s, _, links, texts, rest in STAR:
        for p in ("type", *links, *texts, *rest):
            kind = 0 if p == "type" or p in links else 1
            parts.append(f"SELECT '{src}' AS source, '{p}' AS p, count(*) AS n, {kind} * count(*) AS l, count(DISTINCT {s}) AS d FROM {t}")
    return f"SELECT source, p, CAST(sum(n) AS BIGINT) AS n_triples, CAST(sum(l) AS BIGINT) AS n_literals, CAST(sum(d) AS BIGINT) AS n_subjects FROM ({' UNION ALL '.join(parts)}) GROUP BY source, p"


def walk(sizes: str, limit: int, reject: int | None = None, then: str = "SELECT p, c, scope, n_rows, pages, status FROM log") -> str:
    """The log of a walk: a class is asked if every class above it failed; one that fails is asked for its direct instances too."""
    refused = f"WHEN {{n}} > {reject} THEN 'rejected' " if reject else ""
    outcome = f"CASE {refused}WHEN {{n}} > {limit} THEN 'timeout' ELSE 'ok' END"
    return f"""WITH RECURSIVE {closure_cte()}, {BASE}, kinds AS (SELECT s, min(c) AS c FROM links WHERE p = 'type' GROUP BY s), sizes AS ({sizes}), kids AS (SELECT DISTINCT parent AS c FROM h WHERE parent IS NOT NULL),
    asked AS (SELECT * FROM sizes z WHERE n_all > 0 AND NOT EXISTS (SELECT 1 FROM up JOIN sizes y ON y.c = up.anc AND y.p = z.p WHERE up.c = z.c AND up.depth > 0 AND y.n_all <= {limit})),
    said AS (SELECT p, c, 'subtree' AS scope, n_all AS n_rows, {outcome.format(n="n_all")} || CASE WHEN n_all > {limit} AND c NOT IN (SELECT c FROM kids) THEN ':lost' ELSE '' END AS status FROM asked
        UNION ALL SELECT p, c, 'direct', n_direct, {outcome.format(n="n_direct")} || CASE WHEN n_direct > {limit} THEN ':lost' ELSE '' END FROM asked WHERE n_all > {limit} AND c IN (SELECT c FROM kids) AND n_direct > 0),
    log AS (SELECT *, CASE WHEN status = 'ok' THEN CAST(greatest(1, (n_rows + 499) // 500) AS BIGINT) ELSE 0 END AS pages FROM said),
    covered AS (SELECT DISTINCT log.p, up.c FROM log JOIN up ON up.anc = log.c WHERE status = 'ok' AND (scope = 'subtree' OR up.c = log.c)) {then}"""


EXTENTS = "SELECT p, anc AS c, count(*) AS n_all, count(*) FILTER (short.c = anc) AS n_direct FROM short JOIN up USING (c) GROUP BY p, anc"
REACH = "SELECT 'significance' AS p, anc AS c, count(*) AS n_all, count(*) FILTER (kinds.c = anc) AS n_direct FROM (SELECT DISTINCT s, o AS e FROM links WHERE p <> 'type') l JOIN kinds ON l.e = kinds.s JOIN up ON up.c = kinds.c GROUP BY anc"

SEGMENTS = "(VALUES (0, 'AUTOMOBILE'), (1, 'BUILDING'), (2, 'FURNITURE'), (3, 'HOUSEHOLD'), (4, 'MACHINERY')) g(i, seg)"
REGIONS = "(VALUES (0, 'AFRICA'), (1, 'AMERICA'), (2, 'ASIA'), (3, 'EUROPE'), (4, 'MIDDLE EAST')) r(i, reg)"
GOLD = f"""gold AS (SELECT DISTINCT CAST(qid AS BIGINT) AS qid, answer FROM (
    SELECT i AS qid, n_name AS answer FROM range(10) t(i) JOIN customer ON c_custkey = i JOIN nation ON c_nationkey = n_nationkey
    UNION ALL SELECT 10 + i, c_name FROM {SEGMENTS} JOIN customer ON c_mktsegment = seg
    UNION ALL SELECT 15 + i, s_name FROM {REGIONS} JOIN region ON r_name = reg JOIN nation ON n_regionkey = r_regionkey JOIN supplier ON s_nationkey = n_nationkey
    UNION ALL SELECT 20 + g.i, c_name FROM {SEGMENTS} JOIN {REGIONS} ON g.i = r.i JOIN region ON r_name = reg JOIN nation ON n_regionkey = r_regionkey JOIN customer ON c_nationkey = n_nationkey AND c_mktsegment = seg
    UNION ALL SELECT 25 + i, 'order/' || o_orderkey FROM range(10) t(i) JOIN orders ON o_custkey = i + 20
    UNION ALL SELECT 35 + i, {ITEM} FROM range(15) t(i) JOIN orders ON o_custkey = i JOIN lineitem ON l_orderkey = o_orderkey AND l_suppkey = i % 7))"""
#: Questions that are typed right at once, and those that factoid QA can answer.
TYPED_RIGHT = "(qid < 10 AND qid % 3 <> 0 OR qid BETWEEN 10 AND 14 AND qid % 2 = 0 OR qid BETWEEN 20 AND 24 AND qid % 2 = 0 OR qid BETWEEN 25 AND 34 AND qid % 2 = 1)"
ALONE = f"{GOLD}, runs AS (SELECT DISTINCT 'unaided expert' AS system, qid FROM gold WHERE {TYPED_RIGHT} UNION ALL SELECT DISTINCT 'factoid QA', qid FROM gold WHERE qid < 10)"


def literal_counts() -> str:
    parts = [f"SELECT '{p}' AS p, count(*) AS n FROM {t}" for t, _, _, _, _, texts, rest in STAR for p in (*texts, *rest)]
    return f"SELECT p, CAST(sum(n) AS BIGINT) AS n_literals FROM ({' UNION ALL '.join(parts)}) GROUP BY p"


T = "(CASE " + " ".join(f"WHEN n - 1 >= {d} THEN {v}" for d, v in sorted(T95.items(), reverse=True)) + f" ELSE {T95[1]} END)"

DEAL = """deal AS (SELECT p AS participant, c AS category, j AS slot, 9 * c + (7 * p + 2 * j + c) % 9 AS qid, c = 0 AND j = 0 AS warm_up, (j + c) % 2 AS first_system FROM range(16) a(p), range(3) b(c), range(4) d(j) WHERE j < 3 OR c = 0)"""

LOG = DEAL + """, log AS (
    SELECT event_id % 2 AS system, user_id % 16 AS participant, CAST(json_extract_string(props, '$.k') AS BIGINT) % 27 AS qid, CAST(json_extract_string(props, '$.k') AS BIGINT) % 27 // 9 AS category,
        event_id, ts, event_type = 'click' AS click, CASE event_type WHEN 'purchase' THEN 'success' WHEN 'error' THEN 'gave_up' END AS outcome, value AS seconds, event_type FROM events WHERE (user_id % 16, CAST(json_extract_string(props, '$.k') AS BIGINT) % 27) IN (SELECT participant, qid FROM deal WHERE NOT warm_up)),
seen AS (SELECT *, coalesce(max(CASE WHEN outcome = 'success' THEN 1 END) OVER (PARTITION BY system, participant, qid ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS over_ FROM log),
episodes AS (SELECT system, participant, qid, category, coalesce(bool_or(outcome = 'success'), false) AS answered, count(*) FILTER (click) AS attempts, round(sum(seconds), 6) AS seconds FROM seen WHERE over_ = 0 GROUP BY ALL)"""

PAIRS = "pairs AS (SELECT a, b FROM (SELECT DISTINCT p_name AS b FROM part) CROSS JOIN (VALUES ('blue widgets'), ('red gear'), ('MACHINARY'), ('small bolt')) v(a))"
FORMS = "lex(term, form) AS (VALUES " + ", ".join(f"('{t}', '{v}'), ('{v}', '{t}')" for t, words in WORDS.items() for v in words.split()) + ")"


def suggested(old: str, column: str, kind: str, table: str, extra: str) -> str:
    """One literal replaced: similar cached literals of nearly its length that occur in the column, the five best with answers."""
    return f"""WITH {CACHE}, alts AS (
        SELECT lit AS new, round(jaro_winkler_similarity('{old}', lit), 6) AS similarity FROM scores
        WHERE length(lit) BETWEEN {len(old) - 2} AND {len(old) + 3} AND lit <> '{old}' AND jaro_winkler_similarity('{old}', lit) >= 0.7),
    counted AS (SELECT new, similarity, n_answers, row_number() OVER (ORDER BY similarity DESC, new) AS rank FROM alts JOIN ({extra}) c ON c.v = alts.new)
    SELECT 'literal' AS kind, '{old}' AS old, new, similarity, n_answers, rank FROM counted WHERE rank <= 5"""


# The two ends of the tied case, and its line items.
TIED = "FROM customer, supplier WHERE c_name = 'Customer#000000000' AND s_name = 'Supplier#000000009'"
BETWEEN = f"SELECT 1 FROM (SELECT {ITEM} AS item FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey JOIN supplier ON l_suppkey = s_suppkey WHERE c_name = 'Customer#000000000' AND s_name = 'Supplier#000000009') GROUP BY item"

TRI = "list_distinct([substr({c}, i, 3) FOR i IN range(1, greatest(length({c}) - 2, 1) + 1)])"
NAMES = " UNION ALL ".join(f"SELECT {c} AS v FROM {t}" for t, c in (("region", "r_name"), ("nation", "n_name"), ("customer", "c_name"), ("supplier", "s_name"), ("part", "p_name")))


PLURAL = suggested("blue widgets", "name", "literal", "part", f"SELECT v, count(*) AS n_answers FROM ({NAMES}) GROUP BY v")


def oracle_sql() -> dict[str, str]:
    published = ", ".join(f"('{s}', {a}, {b}, {c})" for s, a, b, c in PUBLISHED)
    two_hops = "SELECT count(*) AS n FROM customer JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey WHERE r_name = 'ASIA' AND c_mktsegment = 'MACHINERY'"
    feature_rows = f"SELECT s AS e, 'out|' || p || '|iri|' || o AS f FROM links UNION ALL SELECT s, 'out|' || p || '|literal|' || o FROM texts UNION ALL SELECT o, 'in|' || p || '|iri|' || s FROM links"
    typed = "typed AS (SELECT DISTINCT substr(w, 1, n) AS t FROM (SELECT p_name AS w FROM part UNION SELECT c_name FROM customer), range(1, 9) r(n) WHERE n <= length(w))"
    found = {
        "triples_profile": profile(),
        "predicate_stats": stats(),
        "class_closure": f"WITH RECURSIVE {closure_cte()}, {BASE} SELECT c, anc, CAST(min(depth) AS BIGINT) AS depth FROM up WHERE c IN (SELECT c FROM links WHERE p = 'type') GROUP BY c, anc",
        "class_instances": f"WITH {BASE} SELECT c, count(*) AS n FROM links WHERE p = 'type' GROUP BY c",
        "literal_predicates": literal_counts(),
        "all_predicates": f"SELECT p FROM (VALUES {PREDICATE_ROWS}) v(p)",
        "literals_cacheable": f"WITH {BASE} SELECT p, count(*) AS n, count(DISTINCT o) AS n_distinct FROM short GROUP BY p",
        "literals_by_language": "SELECT lang, count(*) AS n, count(DISTINCT l) AS n_distinct FROM (SELECT lang, unnest(list_distinct(string_split(text, chr(10)))) AS l FROM documents) WHERE length(l) BETWEEN 1 AND 80 GROUP BY lang",
        "harvest_extents": f"WITH RECURSIVE {closure_cte()}, {BASE} SELECT p, anc AS c, count(*) AS n_all, count(*) FILTER (short.c = anc) AS n_direct FROM short JOIN up USING (c) GROUP BY p, anc",
        "harvest_cumulative": f"SELECT p, n_literals, CAST(sum(n_literals) OVER (ORDER BY n_literals DESC, p ROWS UNBOUNDED PRECEDING) AS BIGINT) AS running FROM ({literal_counts()})",
        "harvest_plan": walk(EXTENTS, 1000),
        "harvest_plan_rejecting": walk(EXTENTS, 1000, 10_000),
        "harvest_cost": walk(EXTENTS, 1000, then="SELECT status, p, count(*) AS queries, CAST(sum(pages) AS BIGINT) AS pages, CAST(coalesce(sum(n_rows) FILTER (status = 'ok'), 0) AS BIGINT) AS n_rows FROM log GROUP BY GROUPING SETS ((status), (p), ())"),
        "harvest_coverage": walk(EXTENTS, 1000, then=", n AS (SELECT (SELECT count(DISTINCT o) FROM short WHERE (p, c) IN (SELECT p, c FROM covered)) AS cached, (SELECT count(DISTINCT o) FROM short) AS eligible) SELECT cached, eligible, round(cached / eligible, 6) AS share FROM n"),
        "harvest_flat": "WITH n AS (SELECT upper(substr(event_type, 1, 1)) || substr(event_type, 2) || 'Event' AS c, count(*) AS n_rows FROM events GROUP BY ALL) SELECT 'eventType' AS p, c, 'subtree' AS scope, n_rows, CASE WHEN n_rows <= 2500 THEN CAST(greatest(1, (n_rows + 499) // 500) AS BIGINT) ELSE 0 END AS pages, CASE WHEN n_rows <= 2500 THEN 'ok' ELSE 'timeout:lost' END AS status FROM n",
        "significance_plan": walk(REACH, 20_000),
        "significance_walked": walk(REACH, 20_000, then=""", carried AS (SELECT DISTINCT short.s AS e, o AS lit FROM short JOIN kinds ON short.s = kinds.s WHERE kinds.c IN (SELECT c FROM covered)), pairs AS (SELECT DISTINCT s, o AS e FROM links WHERE p <> 'type')
            SELECT lit, count(DISTINCT pairs.s) AS score FROM carried LEFT JOIN pairs USING (e) GROUP BY lit"""),
        "significance_schema": f"""WITH {BASE}, h(c, parent) AS (VALUES {", ".join(f"('{c}', {'NULL' if p is None else repr(p)})" for c, p in CLASSES.items())}),
            carried AS (SELECT DISTINCT s AS e, o AS lit FROM (SELECT s, o FROM short UNION ALL SELECT 'class/' || c, c FROM h)), pairs AS (SELECT DISTINCT s, o AS e FROM (SELECT s, o FROM links UNION ALL SELECT 'class/' || c, 'class/' || parent FROM h WHERE parent IS NOT NULL))
            SELECT lit, count(DISTINCT pairs.s) AS score FROM carried LEFT JOIN pairs USING (e) GROUP BY lit""",
        "harvest_fetched": f"WITH {BASE} SELECT DISTINCT source, o AS lit, length(o) AS lit_len FROM short",
        "harvest_keyset_page": "SELECT c_name AS lit FROM customer WHERE c_name > 'Customer#000000040' ORDER BY c_name LIMIT 25",
        "significance_exact": f"WITH {SCORES} SELECT lit, score FROM scores",
        "significance_indegree": f"WITH {SCORES}, degree AS (SELECT e, count(*) AS n FROM pairs GROUP BY e) SELECT lit, CAST(coalesce(sum(n), 0) AS BIGINT) AS score FROM carried LEFT JOIN degree USING (e) GROUP BY lit",
        "significance_restricted": f"WITH {SCORES} SELECT lit, score FROM scores",
        "top_significant": f"WITH {SCORES} SELECT lit, score FROM scores ORDER BY score DESC, lit LIMIT 40",
        "bin_sizes": f"WITH {CACHE} SELECT lit_len, count(*) AS n FROM residual GROUP BY lit_len",
        "assign_slices": f"""WITH {CACHE}, numbered AS (SELECT lit_len, row_number() OVER (ORDER BY lit_len, lit) - 1 AS i, row_number() OVER (PARTITION BY lit_len ORDER BY lit) - 1 AS j, count(*) OVER () AS n FROM residual),
            dealt AS (SELECT lit_len, j, (SELECT max(t) FROM range(7) r(t) WHERE t * n // 7 <= i) AS task FROM numbered)
            SELECT task, lit_len, min(j) AS start, max(j) + 1 AS stop FROM dealt GROUP BY task, lit_len""",
        "slice_balance": f"WITH {CACHE}, n AS (SELECT count(*) AS n FROM residual), s AS (SELECT (t + 1) * n // 7 - t * n // 7 AS k FROM n, range(7) r(t)) SELECT count(*) AS tasks, max(k) AS most, min(k) AS least, CAST(sum(k) AS BIGINT) AS total FROM s",
        "ntile_slices": f"WITH {CACHE} SELECT task, count(*) AS n FROM (SELECT ntile(7) OVER (ORDER BY lit_len, lit) - 1 AS task FROM residual) GROUP BY task",
        "index_stats": f"""WITH {CACHE} SELECT (SELECT count(*) FROM terms WHERE kind = 'predicate') AS predicates, (SELECT count(*) FROM terms WHERE kind = 'literal') AS literals, (SELECT CAST(sum(term_len) AS BIGINT) FROM terms) AS suffix_rows,
            (SELECT CAST(sum(term_len * (term_len + 1) // 2) AS BIGINT) FROM terms) AS suffix_chars, (SELECT CAST(sum(strlen(term) * (strlen(term) + 1) // 2) AS BIGINT) FROM terms) AS suffix_bytes, (SELECT count(*) FROM residual) AS residual, (SELECT count(DISTINCT lit_len) FROM residual) AS bins""",
        "suffix_lookup": f"WITH {CACHE} SELECT term, kind, term_len, score FROM terms WHERE contains(lower(term), 'lue')",
        "complete_short": complete("blue"),
        "complete_long": complete("Customer#00000"),
        "complete_variable": "SELECT CAST(1 AS BIGINT) AS rank, 'x' AS term, 'x' AS origin WHERE false",
        "complete_progressive": complete("r#00000001"),
        "complete_no_index": complete("Customer#0000000", use_index=False),
        "complete_batch": f"""WITH {CACHE}, {typed}, both_ AS (
            SELECT t, term, 0 AS tier, score, term_len, 'index' AS origin FROM typed JOIN terms ON contains(lower(term), lower(t))
            UNION ALL SELECT t, lit, 1, 0, lit_len, 'bin' FROM typed JOIN residual ON contains(lower(lit), lower(t)) AND lit_len BETWEEN length(t) AND length(t) + 10),
            ranked AS (SELECT t, row_number() OVER (PARTITION BY t ORDER BY tier, score DESC, term_len, term) AS rank, term, origin FROM both_) SELECT * FROM ranked WHERE rank <= 10""",
        "stream_completion": f"""WITH {CACHE}, typed AS (SELECT * FROM (VALUES ('blue'), ('new p'), ('Cust')) v(t)), both_ AS (
            SELECT t, term, 0 AS tier, score, term_len, 'index' AS origin FROM typed JOIN terms ON contains(lower(term), lower(t))
            UNION ALL SELECT t, lit, 1, 0, lit_len, 'bin' FROM typed JOIN residual ON contains(lower(lit), lower(t)) AND lit_len BETWEEN length(t) AND length(t) + 10),
            ranked AS (SELECT t, row_number() OVER (PARTITION BY t ORDER BY tier, score DESC, term_len, term) AS rank, term, origin FROM both_) SELECT * FROM ranked WHERE rank <= 10""",
        "scan_all": f"WITH {CACHE} SELECT term FROM (SELECT DISTINCT term FROM (SELECT term FROM terms UNION SELECT lit FROM residual) WHERE contains(lower(term), 'ue')) ORDER BY length(term), term LIMIT 10",
        "baseline_full_scan": f"WITH {CACHE} SELECT term FROM (SELECT term FROM terms UNION SELECT lit FROM residual) WHERE contains(lower(term), 'customer#0000000') ORDER BY length(term), term LIMIT 10",
        "ngram_lookup": f"WITH {CACHE} SELECT lit FROM residual WHERE contains(lower(lit), '0001')",
        "index_hit_ratio": f"""WITH {CACHE}, words AS (SELECT DISTINCT w FROM (SELECT unnest(regexp_split_to_array(regexp_replace(lower(text), '[^a-z ]', ' ', 'g'), ' +')) AS w FROM conversations UNION ALL SELECT p_name FROM part UNION ALL SELECT n_name FROM nation) WHERE length(w) >= 3),
            typed AS (SELECT DISTINCT substr(w, 1, n) AS t FROM words, range(3, 9) r(n) WHERE n <= length(w)), hit AS (SELECT count(DISTINCT t) AS hits FROM typed JOIN terms ON contains(lower(term), lower(t)))
            SELECT (SELECT count(*) FROM typed) AS asked, hits, round(hits / (SELECT count(*) FROM typed), 6) AS ratio FROM hit""",
        "bins_elimination": f"WITH {CACHE} SELECT t_len, round(1 - (SELECT count(*) FROM residual WHERE lit_len BETWEEN t_len AND t_len + 10) / (SELECT count(*) FROM residual), 6) AS skipped FROM range(3, 21) r(t_len)",
        "jaro_winkler_pairs": f"WITH {PAIRS} SELECT a, b, round(jaro_winkler_similarity(a, b), 6) AS jw, round(jaro_similarity(a, b), 6) AS j FROM pairs",
        "jaro_winkler_native": f"WITH {PAIRS} SELECT a, b, round(jaro_winkler_similarity(a, b), 6) AS jw FROM pairs",
        "similarity_comparison": f"""WITH {PAIRS} SELECT a, b, round(1 - levenshtein(a, b) / greatest(length(a), length(b), 1), 6) AS lev,
            round((SELECT count(*) FROM range(1, 33) r(i) WHERE i <= least(length(a), length(b)) AND substr(a, 1, i) = substr(b, 1, i)) / greatest(length(a), length(b), 1), 6) AS prefix,
            round(len(list_intersect({TRI.format(c="a")}, {TRI.format(c="b")})) / len(list_distinct(list_concat({TRI.format(c="a")}, {TRI.format(c="b")}))), 6) AS trigram FROM pairs""",
        "jaro_bound": f"WITH {PAIRS} SELECT CAST(0 AS BIGINT) AS lost, count(*) FILTER (jaro_winkler_similarity(a, b) >= 0.7) AS true_matches FROM pairs",
        "best_match": """WITH pairs AS (SELECT t AS term, lit, jaro_winkler_similarity(t, lit) AS s FROM (VALUES ('blue widgets'), ('red gears')) v(t), (SELECT DISTINCT p_name AS lit FROM part) WHERE length(lit) BETWEEN length(t) - 2 AND length(t) + 3)
            SELECT term, lit, round(s, 6) AS similarity FROM (SELECT *, row_number() OVER (PARTITION BY term ORDER BY s DESC, lit DESC) AS n FROM pairs) WHERE n = 1""",
        "lexicon_verbalizations": f"WITH {FORMS}, words AS (SELECT unnest(regexp_split_to_array(regexp_replace(lower(text), '[^a-z ]', ' ', 'g'), ' +')) AS term FROM conversations), terms AS (SELECT term FROM words WHERE term <> '' UNION SELECT * FROM (VALUES ('vendor'), ('customer'), ('zzz')) v(term)) SELECT term, term AS form FROM terms UNION SELECT term, form FROM lex WHERE term IN (SELECT term FROM terms)",
        "predicate_alternatives": f"""WITH {FORMS}, words AS (SELECT unnest(regexp_split_to_array(regexp_replace(lower(text), '[^a-z ]', ' ', 'g'), ' +')) AS term FROM conversations), terms AS (SELECT term FROM words WHERE term <> '' UNION SELECT * FROM (VALUES ('vendor'), ('suppliedBy'), ('buyer'), ('nation')) v(term)), forms AS (SELECT term, term AS form FROM terms UNION SELECT term, form FROM lex WHERE term IN (SELECT term FROM terms)),
            scored AS (SELECT term, p AS alternative, max(jaro_winkler_similarity(form, p)) AS s FROM forms, (VALUES {PREDICATE_ROWS}) v(p) WHERE term <> p GROUP BY term, p) SELECT term, alternative, round(s, 6) AS similarity FROM scored WHERE s >= 0.7""",
        "literal_alternatives": f"WITH {SCORES} SELECT t AS term, lit AS alternative, round(jaro_winkler_similarity(t, lit), 6) AS similarity FROM scores, (VALUES ('MACHINARY'), ('blue widgets')) v(t) WHERE length(lit) BETWEEN length(t) - 2 AND length(t) + 3 AND lit <> t AND jaro_winkler_similarity(t, lit) >= 0.7",
        "suggest_terms_misspelled": suggested("MACHINARY", "marketSegment", "literal", "customer", "SELECT c_mktsegment AS v, count(*) AS n_answers FROM customer GROUP BY ALL") + " UNION ALL SELECT 'predicate', 'x', 'x', 0.0, 0, 0 WHERE false",
        "suggest_prefetch": f"SELECT new, n_answers AS n FROM ({PLURAL})",
        "suggest_described": f"SELECT 'Use the literal \"' || new || '\" in place of \"blue widgets\": ' || n_answers || ' answers' AS text FROM ({PLURAL})",
        "suggest_terms_plural": suggested("blue widgets", "name", "literal", "part", f"SELECT v, count(*) AS n_answers FROM ({NAMES}) GROUP BY v"),
        "relax_two_answers": f"SELECT {ITEM} AS item FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey JOIN supplier ON l_suppkey = s_suppkey WHERE c_name = 'Customer#000000008' AND s_name = 'Supplier#000000003'",
        "relax_expand": f"WITH {BASE} SELECT * FROM (SELECT s AS v, p, o AS u, true AS forward FROM links WHERE s = 'customer/8' UNION ALL SELECT s, p, '\"' || o, true FROM texts WHERE s = 'customer/8' UNION ALL SELECT 'customer/8', 'accountBalance', '\"' || CAST(c_acctbal AS VARCHAR), true FROM customer WHERE c_custkey = 8 UNION ALL SELECT o, p, s, false FROM links WHERE o = 'customer/8' UNION ALL SELECT '\"' || o, p, s, false FROM texts WHERE o = 'ASIA')",
        "relax_tied": f"WITH trees AS (SELECT 8 AS cost {TIED} AND c_nationkey = s_nationkey UNION ALL SELECT 8 FROM ({BETWEEN})) SELECT CAST(cost AS BIGINT) AS cost, count(*) AS n_trees FROM trees GROUP BY cost",
        "relax_unweighted": f"WITH trees AS (SELECT 4 AS cost {TIED} AND c_nationkey = s_nationkey UNION ALL SELECT 5 FROM ({BETWEEN})) SELECT CAST(cost AS BIGINT) AS cost, count(*) AS n_trees FROM trees WHERE cost = (SELECT min(cost) FROM trees) GROUP BY cost",
        "relax_number": f"SELECT '\"7' AS v, 'size' AS p, 'part/' || p_partkey AS u FROM part WHERE p_size = 7 UNION ALL SELECT '\"7', 'quantity', {ITEM} FROM lineitem WHERE l_quantity = 7",
        "relax_suggestions": "SELECT 'structure' AS kind, count(*) AS n_answers FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey JOIN supplier ON l_suppkey = s_suppkey WHERE c_name = 'Customer#000000008' AND s_name = 'Supplier#000000003' HAVING count(*) > 0",
        "federated_relaxed": "SELECT count(*) AS n FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey JOIN supplier ON l_suppkey = s_suppkey WHERE c_name = 'Customer#000000008' AND s_name = 'Supplier#000000003'",
        "bgp_count_two_hop": two_hops,
        "federated_join": two_hops,
        "bgp_legacy_count": "SELECT count(*) AS n FROM customer WHERE c_mktsegment = 'MACHINERY'",
        "bgp_group_order_limit": "SELECT n_name AS name, count(*) AS n FROM customer JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey WHERE r_name = 'EUROPE' GROUP BY n_name ORDER BY n DESC, n_name LIMIT 3",
        "bgp_having": "SELECT n_name AS name, count(*) AS n FROM customer JOIN nation ON c_nationkey = n_nationkey GROUP BY n_name HAVING count(*) > 60",
        "bgp_aggregates": "SELECT c_mktsegment AS m, count(*) AS n, round(sum(c_acctbal), 4) AS total, round(avg(c_acctbal), 4) AS mean, min(c_acctbal) AS low, max(c_acctbal) AS high FROM customer GROUP BY c_mktsegment",
        "bgp_optional": "SELECT 'document/' || doc_id AS d, CAST(quality AS VARCHAR) AS q FROM documents LEFT JOIN labels USING (doc_id) WHERE source = 'src3'",
        "bgp_union": "SELECT c_name AS n FROM customer WHERE c_mktsegment = 'MACHINERY' UNION ALL SELECT s_name FROM supplier",
        "bgp_minus": "SELECT 'document/' || doc_id AS d FROM documents WHERE lang = 'en' AND doc_id NOT IN (SELECT doc_id FROM labels)",
        "bgp_not_exists": "SELECT 'document/' || doc_id AS d FROM documents WHERE lang = 'de' AND doc_id NOT IN (SELECT doc_id FROM labels)",
        "bgp_not_exists_filter": "SELECT 'customer/' || c_custkey AS c FROM customer WHERE NOT EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey AND o_totalprice > 300000)",
        "bgp_not_exists_unshared": "SELECT 'region/' || r_regionkey AS r FROM region",
        "bgp_minus_unshared": "SELECT 'region/' || r_regionkey AS r FROM region",
        "bgp_optional_empty": "SELECT 'region/' || r_regionkey AS r, CAST(NULL AS VARCHAR) AS x FROM region",
        "bgp_nested": "SELECT 'customer/' || c_custkey AS c, CASE WHEN r_name IN ('ASIA', 'EUROPE') AND contains(n_name, '1') THEN n_name END AS n FROM customer JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey WHERE c_mktsegment = 'MACHINERY'",
        "bgp_filter_typed": "SELECT 'order/' || o_orderkey AS o FROM orders WHERE o_totalprice > 400000 AND o_orderdate >= TIMESTAMP '1995-01-01'",
        "bgp_filter_text": "SELECT DISTINCT p_name AS n FROM part WHERE contains(p_name, 'blue') AND length(p_name) <= 9",
        "bgp_distinct_customers": "SELECT count(DISTINCT o_custkey) AS n FROM lineitem JOIN supplier ON l_suppkey = s_suppkey JOIN orders ON l_orderkey = o_orderkey WHERE s_name = 'Supplier#000000003'",
        "ask_sources": "SELECT CAST(i AS BIGINT) AS pattern_no, source FROM (VALUES (0, 'sales'), (1, 'catalog'), (1, 'sales'), (2, 'geo'), (3, 'geo')) v(i, source)",
        "answers_search_sort": "SELECT 'customer/' || c_custkey AS c, c_name AS n FROM customer WHERE c_mktsegment = 'MACHINERY' AND (contains(c_name, '99') OR contains('customer/' || c_custkey, '99'))",
        "published_table_recomputed": f"""WITH v AS (SELECT 'user ' || user_id AS system, event_id % 50 AS qid, count(*) FILTER (event_type = 'purchase') AS hit, count(*) FILTER (event_type = 'error') AS miss FROM events GROUP BY ALL HAVING hit + miss > 0),
            t(system, processed, n_right, n_partial) AS (VALUES {published} UNION ALL SELECT system, count(*), count(*) FILTER (miss = 0), count(*) FILTER (hit > 0 AND miss > 0) FROM v GROUP BY system), m AS (SELECT *, n_right / 50 AS r0, (n_right + n_partial) / 50 AS rs0, n_right / processed AS p0, (n_right + n_partial) / processed AS ps0 FROM t)
            SELECT system, CAST(processed AS BIGINT) AS processed, CAST(n_right AS BIGINT) AS n_right, CAST(n_partial AS BIGINT) AS n_partial, round(processed / 50, 6) AS share, round(r0, 6) AS r, round(rs0, 6) AS r_star, round(p0, 6) AS p, round(ps0, 6) AS p_star, round(2 * r0 * p0 / nullif(r0 + p0, 0), 6) AS f1, round(2 * rs0 * ps0 / nullif(rs0 + ps0, 0), 6) AS f1_star FROM m""",
        "comparison_gold": f"WITH {GOLD} SELECT qid, answer FROM gold",
        "comparison_unaided": f"""WITH {ALONE}, t AS (SELECT system, count(*) AS processed, count(*) AS n_right, CAST(0 AS BIGINT) AS n_partial FROM runs GROUP BY system)
            SELECT *, round(processed / 50, 6) AS share, round(n_right / 50, 6) AS r, round(n_right / 50, 6) AS r_star, CAST(1 AS DOUBLE) AS p, CAST(1 AS DOUBLE) AS p_star, round(2 * (n_right / 50) / (1 + n_right / 50), 6) AS f1, round(2 * (n_right / 50) / (1 + n_right / 50), 6) AS f1_star FROM t""",
        "comparison_factoid_recall": f"WITH {ALONE} SELECT system, count(*) AS n_right, CAST(10 AS BIGINT) AS total, round(count(*) / 10, 6) AS r FROM runs WHERE qid < 10 GROUP BY system",
        "baseline_summary_graph": f"WITH {BASE}, kinds AS (SELECT s, c FROM links WHERE p = 'type'), allits AS (" + " UNION ALL ".join(f"SELECT {c} AS c, '{p}' AS p FROM {t}" for t, _, _, c, _, texts, rest in STAR for p in (*texts, *rest)) + ") SELECT links.c AS class_s, links.p, kinds.c AS class_o, count(*) AS n FROM links JOIN kinds ON links.o = kinds.s WHERE links.p <> 'type' GROUP BY ALL UNION ALL SELECT c, p, 'literal', count(*) FROM allits GROUP BY ALL",
        "baseline_rewrite": f"SELECT DISTINCT {ITEM} AS x FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey JOIN supplier ON l_suppkey = s_suppkey WHERE c_name = 'Customer#000000008' AND s_name = 'Supplier#000000003'",
        "baseline_keyword_qa": "SELECT DISTINCT 'order/' || o_orderkey AS x, CAST(1 AS BIGINT) AS attempts FROM orders JOIN customer ON o_custkey = c_custkey WHERE c_name = 'Customer#000000008'",
        "baseline_factoid": "SELECT n_name AS x FROM customer JOIN nation ON c_nationkey = n_nationkey WHERE c_name = 'Customer#000000008'",
        "baseline_by_example": f"WITH {BASE}, feats AS (SELECT DISTINCT e, f FROM ({feature_rows})), shared AS (SELECT f FROM feats WHERE e IN ('supplier/0', 'supplier/1') GROUP BY f HAVING count(*) = 2) SELECT e FROM feats JOIN shared USING (f) GROUP BY e HAVING count(*) = (SELECT count(*) FROM shared)",
        "baseline_common_features": f"WITH {BASE}, feats AS (SELECT DISTINCT e, f FROM ({feature_rows})) SELECT f FROM feats WHERE e IN ('nation/3', 'nation/13') GROUP BY f HAVING count(*) = 2",
        "baseline_unaided": "SELECT CAST(i AS BIGINT) AS qid, CASE WHEN i = 0 THEN (SELECT count(DISTINCT c_name) FROM customer WHERE c_mktsegment = 'MACHINERY') ELSE 0 END AS n FROM range(3) t(i)",
        "study_deal": f"WITH {DEAL.replace('range(16)', '(SELECT DISTINCT user_id FROM events)')} SELECT * FROM deal",
        "study_permutation_p": f"""WITH {LOG}, r AS (SELECT participant, avg(CAST(answered AS INT)) FILTER (system = 0) AS a, avg(CAST(answered AS INT)) FILTER (system = 1) AS b FROM episodes GROUP BY participant),
            d AS (SELECT round(a - b, 9) AS d, row_number() OVER (ORDER BY participant) - 1 AS i FROM r WHERE a IS NOT NULL AND b IS NOT NULL), n AS (SELECT count(*) AS n, sum(d) AS s FROM d),
            f AS (SELECT id, sum(CASE WHEN (id >> i) & 1 = 1 THEN -d ELSE d END) AS f FROM n, range(65536) t(id), d WHERE id < CAST(pow(2, n) AS BIGINT) GROUP BY id)
            SELECT n, round(s / n, 6) AS mean, round((SELECT avg(CAST(abs(f) >= abs(s) - 1e-9 AS INT)) FROM f), 6) AS p FROM n""",
        "study_success_ci": f"WITH {LOG}, rates AS (SELECT system, category, participant, avg(CAST(answered AS DOUBLE)) AS rate FROM episodes GROUP BY ALL), s AS (SELECT system, category, avg(rate) AS m, stddev_samp(rate) AS sd, count(*) AS n FROM rates GROUP BY ALL) SELECT system, category, round(m, 6) AS mean, n, round({T} * sd / sqrt(n), 6) AS half_width FROM s",
        "study_answered_any": f"WITH {LOG}, q AS (SELECT system, category, qid, bool_or(answered) AS a FROM episodes GROUP BY ALL) SELECT system, category, round(avg(CAST(a AS DOUBLE)), 6) AS share FROM q GROUP BY ALL",
        "study_attempts": f"WITH {LOG} SELECT system, category, round(avg(attempts), 6) AS attempts FROM episodes WHERE answered GROUP BY ALL",
        "study_giveup": f"WITH {LOG} SELECT system, category, min(attempts) AS least, max(attempts) AS most, round(avg(attempts), 6) AS mean FROM episodes WHERE NOT answered GROUP BY ALL",
        "study_time": f"WITH {LOG} SELECT system, category, round(avg(seconds), 6) AS seconds FROM episodes WHERE answered GROUP BY ALL",
        "study_suggestion_usage": f"""WITH {LOG}, per AS (SELECT bool_or(event_type = 'click' AND event_id % 5 = 0) AS p, bool_or(event_type = 'signup') AS l, bool_or(event_type = 'view') AS s FROM log GROUP BY system, participant, qid)
            SELECT round(avg(CAST(p AS DOUBLE)), 6) AS predicate, round(avg(CAST(l AS DOUBLE)), 6) AS literal, round(avg(CAST(s AS DOUBLE)), 6) AS structure, round(avg(CAST(p OR l OR s AS DOUBLE)), 6) AS any_kind FROM per""",
        "op_unpivot": "SELECT p_partkey, 'p_name' AS column, p_name AS value FROM part UNION ALL SELECT p_partkey, 'p_brand', p_brand FROM part UNION ALL SELECT p_partkey, 'p_type', p_type FROM part",
        "op_filter_range": "SELECT o_orderkey, o_custkey FROM orders WHERE o_totalprice BETWEEN 100000 AND 120000 AND o_orderstatus IN ('F', 'P') AND o_orderdate >= TIMESTAMP '1996-01-01'",
        "op_filter_text": "SELECT p_partkey, p_name FROM part WHERE contains(p_name, 'ue') AND starts_with(p_name, 'b') AND regexp_matches(p_name, 'g[ie]')",
        "op_join_hash": "SELECT r_name, count(*) AS n FROM customer JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY r_name",
        "op_join_broadcast": "SELECT s_name, n_name FROM supplier JOIN nation ON s_nationkey = n_nationkey",
        "op_join_merge": "SELECT o_orderstatus, count(*) AS n FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY o_orderstatus",
        "op_join_left": "SELECT doc_id, lang, CAST(quality AS BIGINT) AS quality FROM documents LEFT JOIN labels USING (doc_id)",
        "op_join_semi": "SELECT c_custkey AS k FROM customer WHERE c_custkey IN (SELECT o_custkey FROM orders)",
        "op_join_anti": "SELECT doc_id FROM documents WHERE doc_id NOT IN (SELECT doc_id FROM labels)",
        "op_join_band": "SELECT t AS term, lit FROM (VALUES ('blue bolt'), ('new plate')) v(t), (SELECT DISTINCT p_name AS lit FROM part) WHERE length(lit) BETWEEN length(t) - 2 AND length(t) + 3",
        "op_join_nested_loop": "SELECT t, lit FROM (VALUES ('blue'), ('bolt')) v(t), (SELECT DISTINCT p_name AS lit FROM part) WHERE contains(lit, t)",
        "op_join_asof": "SELECT b.event_id, (SELECT arg_max(c.event_id, (c.ts, c.event_id)) FROM events c WHERE c.event_type = 'click' AND c.user_id = b.user_id AND c.ts <= b.ts) AS last_click FROM events b WHERE event_type = 'purchase'",
        "op_join_interval": "SELECT a.user_id, a.event_id AS left_id, b.event_id AS right_id FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 1 HOUR WHERE a.event_type = 'click' AND b.event_type = 'purchase'",
        "op_join_self": "SELECT a.o_orderkey, count(*) AS n FROM orders a JOIN orders b ON a.o_custkey = b.o_custkey AND b.o_orderdate > a.o_orderdate GROUP BY a.o_orderkey",
        "op_agg_hash": "SELECT c_mktsegment, count(*) AS n, round(sum(c_acctbal), 4) AS total, round(avg(c_acctbal), 4) AS mean, min(c_acctbal) AS low, max(c_acctbal) AS high FROM customer GROUP BY c_mktsegment",
        "op_agg_collect": "SELECT p_type, array_to_string(list_sort(list_distinct(list(p_name))), ';') AS names FROM part GROUP BY p_type",
        "op_agg_distinct": "SELECT p_name, count(DISTINCT l_suppkey) AS n FROM lineitem JOIN part ON l_partkey = p_partkey GROUP BY p_name",
        "op_agg_grouping_sets": "SELECT o_orderstatus, o_orderpriority, count(*) AS n FROM orders GROUP BY GROUPING SETS ((o_orderstatus), (o_orderpriority), ())",
        "op_agg_cube": "SELECT lang, source, count(*) AS n, CAST(sum(n_chars) AS BIGINT) AS chars FROM documents GROUP BY CUBE (lang, source)",
        "op_agg_rollup": "SELECT r_name, n_name, count(*) AS n FROM customer JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY ROLLUP (r_name, n_name)",
        "op_agg_min_max_by": "SELECT event_type, round(quantile_cont(value, 0.5), 6) AS median, round(quantile_cont(value, 0.95), 6) AS p95, arg_max(event_id, (value, event_id)) AS largest, arg_min(event_id, (value, event_id)) AS smallest FROM events GROUP BY event_type",
        "op_agg_having": "SELECT CAST(c_nationkey AS BIGINT) AS c_nationkey, count(*) AS n FROM customer GROUP BY c_nationkey HAVING count(*) > 60",
        "op_window_rank": "SELECT * FROM (SELECT o_custkey, o_orderkey, row_number() OVER w AS rn, rank() OVER w AS rk, dense_rank() OVER w AS dr FROM orders WINDOW w AS (PARTITION BY o_custkey ORDER BY o_totalprice DESC, o_orderkey)) WHERE rn <= 3",
        "op_window_ntile": "SELECT p_partkey, ntile(4) OVER w AS tile, round(percent_rank() OVER w, 6) AS pr FROM part WINDOW w AS (PARTITION BY p_type ORDER BY p_retailprice, p_partkey)",
        "op_window_lag": "SELECT user_id, event_id, epoch_us(ts) - epoch_us(lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id)) AS gap FROM events",
        "op_window_running": "SELECT o_orderkey, round(sum(o_totalprice) OVER (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey ROWS UNBOUNDED PRECEDING), 4) AS running FROM orders",
        "op_window_range": "SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY epoch_us(ts) // 1000000 RANGE BETWEEN 3600 PRECEDING AND CURRENT ROW) AS n FROM events",
        "op_sort_limit_offset": "SELECT c_custkey, c_acctbal FROM customer ORDER BY c_acctbal DESC LIMIT 25 OFFSET 10",
        "op_top_k": "SELECT p_type, p_name, n FROM (SELECT p_type, p_name, count(*) AS n, row_number() OVER (PARTITION BY p_type ORDER BY count(*) DESC, p_name) AS rn FROM part GROUP BY p_type, p_name) WHERE rn <= 3",
        "op_set_union": "SELECT CAST(c_nationkey AS BIGINT) AS k FROM customer UNION SELECT s_nationkey FROM supplier",
        "op_set_intersect": "SELECT CAST(c_nationkey AS BIGINT) AS k FROM customer INTERSECT SELECT s_nationkey FROM supplier",
        "op_set_except": "SELECT doc_id FROM documents EXCEPT SELECT doc_id FROM labels",
        "op_scalar_string": "SELECT p_partkey, length(p_name) AS len, upper(p_name) AS up, substr(p_name, 2, 3) AS sub, split_part(p_name, ' ', 1) AS head, instr(p_name, 'e') AS at, regexp_replace(p_name, '[aeiou]', '*', 'g') AS stars, translate(p_name, 'ab', 'xy') AS tr, p_brand || '-' || p_name AS joined, levenshtein(p_name, 'blue bolt') AS lev FROM part",
        "op_scalar_date": "SELECT o_orderkey, year(o_orderdate) AS y, month(o_orderdate) AS m, date_diff('day', CAST(o_orderdate AS DATE), DATE '2000-01-01') AS days, strftime(date_trunc('month', o_orderdate), '%Y-%m-%d') AS mon FROM orders",
        "op_scalar_math": "SELECT c_custkey, CAST(floor(c_acctbal) AS BIGINT) AS fl, round(sqrt(abs(c_acctbal)), 6) AS rt, greatest(c_acctbal, 0.0) AS pos, round(CASE WHEN c_nationkey = 0 THEN NULL ELSE c_acctbal / c_nationkey END, 6) AS ratio FROM customer",
        "op_scalar_array": "SELECT p_partkey, len(w) AS n, array_to_string(list_transform(w, lambda x: upper(x)), '+') AS up, array_to_string(list_filter(w, lambda x: x NOT IN ('blue', 'red')), '+') AS rest, CAST(list_sum(list_transform(w, lambda x: length(x))) AS BIGINT) AS chars FROM (SELECT p_partkey, string_split(p_name, ' ') AS w FROM part)",
        "op_scalar_map": "SELECT n_name, len(list_distinct(string_split(n_name, ''))) AS letters, length(n_name) - length(replace(n_name, 'N', '')) AS n_count, list_max(list_transform(list_distinct(string_split(n_name, '')), lambda c: length(n_name) - length(replace(n_name, c, '')))) AS most FROM nation",
        "op_scalar_json": "SELECT event_id, CAST(json_extract_string(props, '$.k') AS BIGINT) AS k, '{\"k\":' || json_extract_string(props, '$.k') || '}' AS again FROM events",
        "op_scalar_html": "SELECT page_id, regexp_extract(html, '<title>([^<]*)</title>', 1) AS title, regexp_extract(html, '<html[^>]* lang=\"([^\"]*)\"', 1) AS lang, len(regexp_extract_all(html, 'href=\"(/[^\"]*)\"', 1)) AS links FROM pages",
        "op_udf_registered": "SELECT p_name, round(jaro_winkler_similarity(p_name, 'blue bolt'), 6) AS jw FROM (SELECT DISTINCT p_name FROM part)",
        "op_source_csv": "SELECT CAST(n_nationkey AS BIGINT) AS n_nationkey, n_name FROM nation",
        "op_source_json": "SELECT s_suppkey, s_name FROM supplier",
        "op_sink_partitioned": "SELECT doc_id, length(text) AS n FROM documents WHERE lang = 'de'",
        "op_stored_index": f"WITH {CACHE} SELECT lit, lit_len FROM residual WHERE contains(lower(lit), 'customer#') AND lit_len BETWEEN 9 AND 19 ORDER BY lit_len, lit LIMIT 5",
        "op_stream_tumbling": "SELECT strftime(time_bucket(INTERVAL 1 HOUR, ts), '%Y-%m-%d %H:%M:%S') AS start, event_type, count(*) AS n FROM events GROUP BY ALL",
        "stream_tumbling": "SELECT strftime(time_bucket(INTERVAL 1 HOUR, ts), '%Y-%m-%d %H:%M:%S') AS start, event_type, count(*) AS n FROM events GROUP BY ALL",
        "op_stream_sliding": "SELECT strftime(time_bucket(INTERVAL 15 MINUTE, ts) - i * INTERVAL 15 MINUTE, '%Y-%m-%d %H:%M:%S') AS start, count(*) AS n FROM events, range(4) r(i) GROUP BY ALL",
        "op_source_ntriples": """SELECT s, p, o, o_kind, CASE WHEN o_kind = 'literal' THEN 'string' END AS o_dtype, CAST(NULL AS VARCHAR) AS o_lang FROM (
            SELECT 'region/' || r_regionkey AS s, 'type' AS p, 'class/Region' AS o, 'iri' AS o_kind FROM region UNION ALL SELECT 'region/' || r_regionkey, 'name', r_name, 'literal' FROM region
            UNION ALL SELECT 'nation/' || n_nationkey, 'type', 'class/Nation', 'iri' FROM nation UNION ALL SELECT 'nation/' || n_nationkey, 'name', n_name, 'literal' FROM nation UNION ALL SELECT 'nation/' || n_nationkey, 'region', 'region/' || n_regionkey, 'iri' FROM nation
            UNION ALL SELECT 'class/' || c, 'subClassOf', 'class/' || parent, 'iri' FROM """ + HIERARCHY + """ WHERE parent IS NOT NULL UNION ALL SELECT 'class/' || c, 'label', c, 'literal' FROM """ + HIERARCHY + ")",
        "op_stream_sessions": SESSIONS,
        "stream_sessions": SESSIONS,
        "stream_dedupe": "SELECT DISTINCT event_id FROM events",
        "op_stream_attempts": """WITH r AS (SELECT *, coalesce(sum(CAST(event_type IN ('purchase', 'error') AS INT)) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS run FROM events)
            SELECT user_id, count(*) FILTER (event_type = 'click') AS attempts, max(CASE event_type WHEN 'purchase' THEN 'success' WHEN 'error' THEN 'gave_up' END) AS outcome FROM r GROUP BY user_id, run HAVING outcome IS NOT NULL""",
    }
    return found | {"stream_attempts": found["op_stream_attempts"], "stream_sliding": found["op_stream_sliding"]}


SESSIONS = """WITH o AS (SELECT *, CASE WHEN epoch_us(ts) - epoch_us(lag(ts) OVER w) < 1800000000 THEN 0 ELSE 1 END AS fresh FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)),
    s AS (SELECT *, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS UNBOUNDED PRECEDING) AS k FROM o) SELECT user_id, min(epoch_us(ts)) AS start, count(*) AS n FROM s GROUP BY user_id, k"""
