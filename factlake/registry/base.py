"""Registration of queries with their DuckDB SQL, and SQL fragments that several share."""

from __future__ import annotations

from collections.abc import Callable
from math import gcd

QUERIES: dict[str, Callable] = {}
ORACLES: dict[str, str] = {}


def query(name: str, sql: str | None = None):
    def add(f):
        QUERIES[name] = f
        if sql:
            ORACLES[name] = sql
        return f

    return add


def _case(column: str, values: dict[str, object]) -> str:
    return f"CASE {column} " + " ".join(f"WHEN '{k}' THEN {v!r}" for k, v in values.items()) + " END"


CLASS = {"1-URGENT": "official_db", "2-HIGH": "policy", "3-MEDIUM": "tech_doc", "4-NOT SPECIFIED": "wiki", "5-LOW": "chat"}
PRIOR = {"official_db": 0.95, "policy": 0.90, "tech_doc": 0.80, "wiki": 0.60, "chat": 0.30}
NOW = "TIMESTAMP '2001-08-02'"


def order_units(rate: float | None = None) -> str:
    """CTEs ending in u: the order corpus."""
    keep = "" if rate is None else f"WHERE source <> 'chat' OR (o_orderkey * 37) % 100 < {rate * 100}"
    return f"""
    src AS (SELECT o_orderkey, o_custkey AS topic, o_orderdate AS born_at, o_totalprice AS value, {_case('o_orderpriority', CLASS)} AS source FROM orders),
    u0 AS (SELECT *, source = 'chat' AS is_rumour FROM src {keep}),
    u1 AS (SELECT 'O:' || o_orderkey AS unit_id, topic, CASE WHEN NOT is_rumour THEN CAST(row_number() OVER w AS BIGINT) END AS version_no, born_at, born_at AS valid_from,
        CASE WHEN NOT is_rumour THEN lead(born_at) OVER w END AS valid_to, value, source, is_rumour,
        CASE WHEN NOT is_rumour THEN 'O:' || lag(o_orderkey) OVER w END AS replaces, CASE WHEN NOT is_rumour THEN 'O:' || lead(o_orderkey) OVER w END AS replaced_by,
        {_case('source', PRIOR)} AS prior_trust FROM u0 WINDOW w AS (PARTITION BY topic, is_rumour ORDER BY born_at, o_orderkey)),
    u AS (SELECT *, CASE WHEN replaced_by IS NULL THEN 'ACTIVE' ELSE 'DEPRECATED' END AS status,
        CAST((CASE WHEN replaces IS NULL THEN 0 ELSE 1 END) + (CASE WHEN replaced_by IS NULL THEN 0 ELSE 1 END) AS BIGINT) AS degree FROM u1)"""


QUERY_SET = f""",
    lastv AS (SELECT topic, max_by(unit_id, version_no) AS truth, max(born_at) AS newest FROM u WHERE NOT is_rumour GROUP BY topic),
    widev AS (SELECT *, count(*) OVER (PARTITION BY topic) AS n, row_number() OVER (PARTITION BY topic ORDER BY version_no) AS r FROM u WHERE NOT is_rumour AND (valid_to IS NULL OR valid_to > valid_from)),
    qs AS (SELECT 'current' AS kind, topic, {NOW} AS ref_time, truth FROM lastv
        UNION ALL SELECT 'time_point', topic, valid_from + to_days(CAST(floor((epoch_us(coalesce(valid_to, {NOW})) - epoch_us(valid_from)) / 86400000000.0 / 2) AS INTEGER)), unit_id FROM widev WHERE r = ceil(n / 2.0)
        UNION ALL SELECT 'conflict', l.topic, {NOW}, truth FROM lastv l JOIN (SELECT topic, max(born_at) AS said FROM u WHERE is_rumour GROUP BY topic) r ON l.topic = r.topic AND said > newest),
    queries AS (SELECT *, substr(kind, 1, 3) || ':' || topic AS query_id FROM qs)"""

ORDER_TEXT = """,
    tt AS (SELECT c_custkey AS topic, 'acct' || c_custkey || ' ' || lower(c_mktsegment) || ' ' || lower(replace(n_name, ' ', '')) AS text FROM customer JOIN nation ON c_nationkey = n_nationkey),
    bodies AS (SELECT unit_id, text || ' ' || replace(source, '_', '') || ' v' || CAST(floor(value) AS BIGINT) AS body FROM u JOIN tt USING (topic)),
    asked AS (SELECT query_id, text FROM queries JOIN tt USING (topic))"""


def random_sql(seed: int, salt: str, topic: str = "topic") -> str:
    """The portable random number, as one expression."""
    p = 2**31 - 1
    x = f"(({seed} * 7919 + 1 + CAST({topic} AS BIGINT) * 104729 + CAST({salt} AS BIGINT) * 1299709) % {p})"
    y = f"(({x} * {x} + 48271 * {x}) % {p})"
    z = f"((16807 * {y}) % {p})"
    return f"((({z} * {z} + {y}) % {p}) / {float(p)})"


SUPPLIERS = "SELECT s_suppkey AS topic FROM supplier"


def policy_units(topics: int = 60, versions: int = 4, rate: float = 0.3, seed: int = 7, given: str = "") -> str:
    """CTEs ending in u and bodies: the generated corpus; ``given`` selects its topics from a table."""
    r = lambda salt: random_sql(seed, str(salt))
    gap = lambda k: f"(40 + CAST(floor({r(k)} * 51) AS BIGINT))"
    spread = " + ".join(gap(k) for k in range(2, versions + 1))
    newest = f"CASE WHEN {r(52)} < 0.6 THEN 12 + CAST(floor({r(51)} * 60) AS BIGINT) ELSE greatest(12, 240 + CAST(floor({r(50)} * 181) AS BIGINT) - ({spread})) END"
    age = " + ".join([newest, *(f"CASE WHEN v < {k} THEN {gap(k)} ELSE 0 END" for k in range(2, versions + 1))])
    names = "['official_db', 'policy', 'tech_doc', 'wiki']"
    n = lambda salt, most: f"CAST(floor({r(salt)} * {most}) AS BIGINT)"
    said = f"(topic * {rumour_step(topics)} + {seed * 11}) % {topics} < {round(rate * topics)}"
    before, after = ("topic - 1 IN (SELECT topic FROM t)", "topic + 1 IN (SELECT topic FROM t)") if given else ("topic > 0", f"topic + 1 < {topics}")
    noun = "'policy topic' || topic || ' clause' || (topic % 20)"
    return f"""
    t AS ({given or f"SELECT CAST(range AS BIGINT) AS topic FROM range({topics})"}),
    gen AS (SELECT topic, v AS version_no, {NOW} - to_days(CAST({age} AS INTEGER)) AS born_at, CAST(100 + floor({r(41)} * 900) + (v - 1) * (5 + floor({r(40)} * 20)) AS DOUBLE) AS value,
        {names}[CAST(floor({r('v + 60')} * 4) AS INTEGER) + 1] AS source, FALSE AS is_rumour, {n('v + 80', 14)} AS pos_n, {n('v + 90', 3)} AS neg_n, {n('v + 100', 30)} AS access_n, CASE WHEN v = {versions} AND {r(70)} < 0.3 THEN ' current' ELSE '' END AS mark
        FROM t, (SELECT CAST(range AS BIGINT) AS v FROM range(1, {versions + 1})) vs
        UNION ALL SELECT topic, NULL, {NOW} - to_days(CAST(1 + floor({r(98)} * 10) AS INTEGER)), CAST(100 + floor({r(41)} * 900) + 500 AS DOUBLE), 'chat', TRUE, {n(85, 3)}, 0, 0, CASE WHEN {r(71)} < 0.2 THEN ' current' ELSE '' END FROM t WHERE {said}),
    u1 AS (SELECT CASE WHEN is_rumour THEN 'P:' || topic || ':r' ELSE 'P:' || topic || ':' || version_no END AS unit_id, topic, version_no, born_at, born_at AS valid_from,
        CASE WHEN NOT is_rumour THEN lead(born_at) OVER w END AS valid_to, value, source, is_rumour,
        CASE WHEN NOT is_rumour THEN 'P:' || topic || ':' || lag(version_no) OVER w END AS replaces, CASE WHEN NOT is_rumour THEN 'P:' || topic || ':' || lead(version_no) OVER w END AS replaced_by,
        {_case('source', PRIOR)} AS prior_trust, pos_n, neg_n, access_n, mark FROM gen WINDOW w AS (PARTITION BY topic, is_rumour ORDER BY born_at, version_no)),
    u AS (SELECT * EXCLUDE (mark), CASE WHEN replaced_by IS NULL THEN 'ACTIVE' ELSE 'DEPRECATED' END AS status,
        CAST((CASE WHEN replaced_by IS NULL AND NOT is_rumour AND topic % 5 = 0 AND {before} THEN 1 ELSE 0 END) + (CASE WHEN replaced_by IS NULL AND NOT is_rumour AND (topic + 1) % 5 = 0 AND {after} THEN 1 ELSE 0 END) AS BIGINT) AS degree,
        CASE WHEN is_rumour THEN 'heard policy topic' || topic || mark || ' goes to value' || CAST(floor(value) AS BIGINT) || ' soon chat' ELSE {noun} || ' area' || topic || ' limit' || mark || ' value' || CAST(floor(value) AS BIGINT) END AS body FROM u1),
    bodies AS (SELECT unit_id, body FROM u)"""


def rumour_step(topics: int) -> int:
    """A step that visits every topic once: the smallest number from 37 on without a common factor."""
    return next(k for k in range(37, 37 + topics + 1) if gcd(k, topics) == 1)


POLICY_ASKED = """,
    asked AS (SELECT query_id, 'policy topic' || topic || ' clause' || (topic % 20) || ' area' || topic || ' current limit' AS text FROM queries)"""


def tfidf(k: int = 8) -> str:
    """CTEs ending in cand(query_id, unit_id, sim, first_rank), from bodies and asked; equal texts are scored once."""
    terms = lambda src, key, text: f"(SELECT {key}, unnest(list_concat(w, list_transform(range(1, len(w)), lambda i: w[i] || ' ' || w[i + 1]))) AS term FROM (SELECT {key}, regexp_extract_all(lower({text}), '[\\p{{L}}0-9]+') AS w FROM {src}))"
    return f""",
    tf AS (SELECT unit_id, term, count(*) AS tf FROM {terms('bodies', 'unit_id', 'body')} GROUP BY ALL),
    idf AS (SELECT term, ln((1.0 + n) / (1.0 + df)) + 1.0 AS idf FROM (SELECT term, count(*) AS df FROM tf GROUP BY term), (SELECT count(*) AS n FROM bodies)),
    raw AS (SELECT unit_id, term, tf * idf AS x FROM tf JOIN idf USING (term)),
    post AS (SELECT term, unit_id, x / norm AS w FROM raw JOIN (SELECT unit_id, sqrt(sum(x * x)) AS norm FROM raw GROUP BY unit_id) USING (unit_id)),
    texts AS (SELECT DISTINCT text FROM asked),
    qraw AS (SELECT text, term, tf * idf AS x FROM (SELECT text, term, count(*) AS tf FROM {terms('texts', 'text', 'text')} GROUP BY ALL) JOIN idf USING (term)),
    qw AS (SELECT text, term, x / norm AS wq FROM qraw JOIN (SELECT text, sqrt(sum(x * x)) AS norm FROM qraw GROUP BY text) USING (text)),
    sims AS (SELECT text, unit_id, round(sum(wq * w), 9) AS sim FROM qw JOIN post USING (term) GROUP BY ALL),
    near AS (SELECT * FROM (SELECT *, row_number() OVER (PARTITION BY text ORDER BY sim DESC, unit_id) AS first_rank FROM sims) WHERE first_rank <= {k}),
    cand AS (SELECT query_id, unit_id, sim, first_rank FROM asked JOIN near USING (text))"""


def days(a: str, b: str) -> str:
    return f"greatest(0.0, floor((epoch_us({b}) - epoch_us({a})) / 86400000000.0))"


def live_trust(half_life: float = 30.0) -> str:
    """Trust of units with counts of feedback and access, at NOW."""
    return f"least(1.0, least(1.0, greatest(0.01, prior_trust * pow(2.0, -{days('born_at', NOW)} / {half_life}) + 0.03 * pos_n - 0.08 * neg_n)) + 0.01 * ln(1.0 + access_n))"


def scored(half_life: float = 30.0, exclude_future: bool = False, floor_in_window: bool = False, feedback: bool = False) -> str:
    """CTE sc: candidates with all signals; ``feedback``: u has counts of feedback and access."""
    used = lambda x: f"least(1.0, {x} + 0.01 * ln(1.0 + access_n))" if feedback else x
    said = " + 0.03 * pos_n - 0.08 * neg_n" if feedback else ""
    rec = f"pow(2.0, -{days('born_at', 'ref_time')} / {half_life})"
    tmp = f"greatest({rec}, 0.05)" if floor_in_window else rec
    return f""",
    sc AS (SELECT c.query_id, c.unit_id, sim, kind, ref_time, truth, u.*EXCLUDE (unit_id),
        CASE WHEN ref_time >= valid_from AND (valid_to IS NULL OR ref_time <= valid_to) THEN {tmp} ELSE 0.05 END AS temporal,
        {used(f"least(1.0, greatest(0.01, prior_trust * {rec}{said}))")} AS trust, least(0.3, 0.1 * ln(1.0 + degree)) AS relational
        FROM cand c JOIN queries q ON c.query_id = q.query_id JOIN u ON c.unit_id = u.unit_id {'WHERE born_at <= ref_time' if exclude_future else ''})"""


def score(w: tuple[float, float, float, float]) -> str:
    names = ("sim", "temporal", "trust", "relational")
    return "round(" + " + ".join(f"{n} * {float(x)!r}" for n, x in zip(names, w, strict=True) if x) + ", 9)"


def ranked(w, k: int = 1, name: str = "top") -> str:
    return f""",
    {name} AS (SELECT * FROM (SELECT *, CAST(row_number() OVER (PARTITION BY query_id ORDER BY final DESC, sim DESC, unit_id) AS BIGINT) AS rank FROM (SELECT *, {score(w)} AS final FROM sc)) WHERE rank <= {k})"""


def judged(conf: str = "trust", top: str = "top", name: str = "j") -> str:
    return f""",
    {name} AS (SELECT q.query_id, q.kind, t.{conf} AS conf, CASE WHEN t.unit_id = q.truth THEN 1.0 ELSE 0.0 END AS "right", CASE WHEN t.status = 'DEPRECATED' THEN 1.0 ELSE 0.0 END AS stale, CASE WHEN t.is_rumour THEN 1.0 ELSE 0.0 END AS misled
        FROM queries q LEFT JOIN {top} t ON q.query_id = t.query_id)"""


def summary(src: str = "j", by: str = "") -> str:
    of = lambda k: f"round(avg(CASE WHEN kind = '{k}' THEN \"right\" END), 6) AS {k}"
    return f"""SELECT {by + ', ' if by else ''}count(*) AS n, round(avg("right"), 6) AS overall, {of('current')}, {of('time_point')}, {of('conflict')},
        round(avg(CASE WHEN kind = 'current' THEN stale END), 6) AS stale, round(avg(CASE WHEN kind IN ('current', 'conflict') THEN misled END), 6) AS misled FROM {src} {'GROUP BY ' + by if by else ''}"""


ECE = """SELECT round(sum(n * abs(c - a)) / sum(n), 6) AS ece FROM (SELECT least(floor(conf * 10), 9) AS bin, count(*) AS n, avg(conf) AS c, avg("right") AS a FROM j WHERE conf IS NOT NULL GROUP BY 1)"""

def orders(half_life: float = 30.0, k: int = 8, rate: float | None = None, **more) -> str:
    """WITH clause: the order corpus up to sc."""
    return "WITH " + order_units(rate) + QUERY_SET + ORDER_TEXT + tfidf(k) + scored(half_life, **more)


def policies(half_life: float = 30.0, k: int = 8, rate: float = 0.3, seed: int = 7, given: str = "", **more) -> str:
    return "WITH " + policy_units(rate=rate, seed=seed, given=given) + QUERY_SET + POLICY_ASKED + tfidf(k) + scored(half_life, feedback=True, **more)
