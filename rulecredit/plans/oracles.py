"""The same results as plain SQL over the tables, built from common table expressions.

Where the engine uses one form of a measure, the SQL uses another: contributions of
the decomposed form are checked by summing over pruned coalitions and the other way round.
"""

from __future__ import annotations

from rulecredit.operators.evaluation import BANDS, ROBUSTNESS, Instance
from rulecredit.plans.fixtures import MEASURED, RULES
from rulecredit.plans.workbench import SETTINGS, Setting


def _ladder(c: str, cuts: list[float]) -> str:
    rungs = " ".join(f"WHEN {c} >= {cut} THEN '{i}'" for i, cut in reversed(list(enumerate(cuts, 1))))
    return f"CASE WHEN {c} IS NULL THEN NULL {rungs} ELSE '0' END"


def _has(c: str, s: str) -> str:
    return f"(instr({c}, {s}) > 0)::VARCHAR"


EVENT_COLUMNS = {
    "et": "event_type",
    "h": "(hour(ts) // 6)::VARCHAR",
    "dow": "(dayofweek(ts) + 1)::VARCHAR",
    "v": _ladder("value", [20, 50]),
    "u": "(user_id // 50)::VARCHAR",
    "k": "(regexp_extract(props, '\"k\": *([0-9]+)', 1)::INT // 25)::VARCHAR",
}

VIEW_COLUMNS: dict[str, tuple[str, dict[str, str]]] = {
    "conversations": (
        "conversations",
        {
            "role": "role",
            "turn": "least(turn, 3)::VARCHAR",
            "len": "CASE WHEN length(text) < 100 THEN 's' WHEN length(text) < 300 THEN 'm' ELSE 'l' END",
            "qm": _has("text", "'?'"),
            "nl": _has("text", "chr(10)"),
        },
    ),
    "documents": (
        "documents LEFT JOIN labels USING (doc_id)",
        {
            "lang": "lang",
            "nc": _ladder("n_chars", [300, 1500, 5000]),
            "source": "source",
            "q": "quality::VARCHAR",
            "t": "toxic::VARCHAR",
            "hu": _has("text", "'http'"),
            "em": _has("text", "'@'"),
            "pi": _has("text", "'|'"),
        },
    ),
    "events": ("events", EVENT_COLUMNS),
    "pages": (
        "pages",
        {
            "sch": "split_part(url, ':', 1)",
            "hl": "regexp_extract(html, 'lang=\"([a-z]+)\"', 1)",
            "tb": _has("html", "'<table'"),
            "sc": _has("html", "'<script'"),
            "nav": _has("html", "'<nav'"),
            "len": "least(length(html) // 1500, 3)::VARCHAR",
        },
    ),
    "embeddings": (
        "embeddings",
        {"lab": "label::VARCHAR"}
        | {f"x{i}": f"least(greatest(floor((embedding[{i}]::DOUBLE + 0.3) / 0.2), 0), 2)::BIGINT::VARCHAR" for i in range(1, 9)},
    ),
    "star": (
        "lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey "
        "JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey JOIN part ON l_partkey = p_partkey",
        {
            "rf": "l_returnflag",
            "ls": "l_linestatus",
            "q": "floor(l_quantity / 17)::BIGINT::VARCHAR",
            "ep": "floor(least(l_extendedprice, 99999.0::DOUBLE) / 35000)::BIGINT::VARCHAR",
            "os": "o_orderstatus",
            "seg": "c_mktsegment",
            "reg": "r_name",
            "nat": "n_name",
            "pt": "p_type",
            "ps": "((p_size - 1) // 17)::VARCHAR",
            "pr": "floor((p_retailprice - 900) / 34)::BIGINT::VARCHAR",
        },
    ),
}

SCORES = {"is": "sqrt(sup * lift)", "is_product": "sup * lift", "confidence": "conf", "lift": "lift", "support": "sup"}
AGGS = {
    "max": "max(score)",
    "sum": "sum(score)",
    "avg": "avg(score)",
    "top2": "list_sum(list_slice(list_reverse_sort(list(score)), 1, 2))",
    "top3": "list_sum(list_slice(list_reverse_sort(list(score)), 1, 3))",
}


def attribute(e: str) -> str:
    return f"split_part({e}, '=', 1)"


def value_of(e: str) -> str:
    return f"substr({e}, instr({e}, '=') + 1)"


def rounded(e: str) -> str:
    return f"(round({e}, 6) + 0.0)"


def view_ctes(view: str, where: str = "") -> str:
    """v, t (compressed tuples), el (tuple elements)."""
    source, cols = VIEW_COLUMNS[view]
    picked = ", ".join(f"{e} AS \"{c}\"" for c, e in cols.items())
    names = ", ".join(f'"{c}"' for c in cols)
    parts = " UNION ALL ".join(f"SELECT rid, c, '{c}=' || \"{c}\" AS e FROM t WHERE \"{c}\" IS NOT NULL" for c in cols)
    return f"""v AS (SELECT {picked} FROM {source} {where}),
t AS MATERIALIZED (SELECT row_number() OVER () AS rid, * FROM (SELECT {names}, count(*) AS c FROM v GROUP BY ALL)),
nn AS (SELECT coalesce(sum(c), 0)::BIGINT AS n FROM t),
el AS ({parts})"""


def level_ctes(max_len: int, group: str = "", least: str = "") -> str:
    """s1.., i1.. level by level: tuples with a frequent itemset and its last element, and the itemsets; i_all has all.

    Over fel (group, rid, c, e); ``least``: the HAVING condition, for a group joined to its row of nn.
    """
    g = f"{group}, " if group else ""
    same = f"f.{group} = s.{group} AND " if group else ""
    n = f"JOIN nn USING ({group})" if group else ", nn"
    levels = [f"s1 AS MATERIALIZED (SELECT {g}rid, c, [e] AS items, e AS last FROM fel)"]
    for k in range(1, max_len + 1):
        levels.append(f"i{k} AS MATERIALIZED (SELECT {g}items, sum(c)::BIGINT AS cnt, any_value(n) AS n FROM s{k} {n} GROUP BY {g}items HAVING {least})")
        if k < max_len:
            levels.append(
                f"s{k + 1} AS MATERIALIZED (SELECT {'s.' + g if g else ''}s.rid, s.c, list_append(s.items, f.e) AS items, f.e AS last "
                f"FROM (SELECT * FROM s{k} SEMI JOIN i{k} USING ({g}items)) s JOIN fel f ON {same}f.rid = s.rid AND f.e > s.last)"
            )
    found = " UNION ALL ".join(f"SELECT {g}items, {k}::INT AS size, cnt, n FROM i{k}" for k in range(1, max_len + 1))
    return ",\n".join(levels) + f",\ni_all AS MATERIALIZED ({found})"


def itemset_ctes(view: str, setting: Setting | None = None, where: str = "") -> str:
    s = setting or SETTINGS[view]
    pct = round(s.min_support * 100)
    return f"""{view_ctes(view, where)},
fe AS (SELECT e, sum(c)::BIGINT AS cnt FROM el GROUP BY e HAVING sum(c) * 100 >= {pct} * (SELECT n FROM nn)),
fel AS MATERIALIZED (SELECT rid, c, e FROM el SEMI JOIN fe USING (e)),
{level_ctes(s.max_len, least=f'sum(c) * 100 >= {pct} * any_value(n)')},
its AS (SELECT items, size, cnt FROM i_all)"""


def rule_ctes(view: str, score: str = "is", agg: str = "max", setting: Setting | None = None, where: str = "", keep: str = "TRUE") -> str:
    """its, rs (scored rules), val (itemset values), ee (elements in rules), wt (weights by size)."""
    s = setting or SETTINGS[view]
    return f"""{itemset_ctes(view, setting, where)},
sp AS (SELECT items, size, cnt, unnest(range(1, (1 << size) - 1)) AS m FROM its WHERE size >= 2),
sd AS (SELECT *, list_filter(items, lambda x, i: ((m >> (i - 1)::INT) & 1) = 1) AS lhs,
              list_filter(items, lambda x, i: ((m >> (i - 1)::INT) & 1) = 0) AS rhs FROM sp),
rc AS (SELECT sd.items, sd.size, sd.cnt, lhs, rhs, l.cnt AS lc, h.cnt AS hc, n FROM sd JOIN its l ON l.items = lhs JOIN its h ON h.items = rhs, nn),
rm AS (SELECT *, cnt::DOUBLE / n AS sup, cnt::DOUBLE / lc AS conf, (cnt::DOUBLE * n) / (lc::DOUBLE * hc) AS lift FROM rc),
rs AS (SELECT *, {SCORES[score]} AS score FROM rm WHERE greatest(lift, 1 / lift) >= {s.min_lift} AND ({keep})),
{value_ctes(agg)}"""


def value_ctes(agg: str = "max") -> str:
    return f"""val AS (SELECT items, size, count(*) AS n_rules, {AGGS[agg]} AS v FROM rs GROUP BY items, size),
ee AS (SELECT DISTINCT unnest(items) AS e FROM val),
{weight_ctes()}"""


def weight_ctes() -> str:
    return """en AS (SELECT count(*) AS n FROM ee),
wt AS (SELECT k, 1.0::DOUBLE / (n * coalesce(list_aggregate(list_transform(range(1, k + 1), lambda i: (n - i)::DOUBLE / i), 'product'), 1.0)) AS w
       FROM en, (SELECT unnest(range(0, 12)) AS k) WHERE k < n)"""


def pruned_ctes() -> str:
    """x over pruned coalitions."""
    return f"""co AS (SELECT items FROM val UNION SELECT list_filter(items, lambda y, i: i <> j) FROM val, (SELECT unnest(range(1, 12)) AS j) WHERE j <= size),
pr AS (SELECT e, co.items FROM co, ee WHERE len(list_filter(co.items, lambda y: {attribute('y')} = {attribute('e')})) = 0),
x AS (SELECT e, sum(w * (coalesce(v1.v, 0) - coalesce(v0.v, 0))) AS x FROM pr
      JOIN wt ON wt.k = len(pr.items) LEFT JOIN val v0 ON v0.items = pr.items
      LEFT JOIN val v1 ON v1.items = list_sort(list_append(pr.items, e)) GROUP BY e)"""


def decomposed_ctes() -> str:
    """x from sums by element, by attribute and over all itemsets."""
    return f"""pe AS (SELECT e, sum(w * v) AS p FROM (SELECT unnest(items) AS e, size, v FROM val) JOIN wt ON k = size - 1 GROUP BY e),
aa AS (SELECT a, sum(w * v) AS s FROM (SELECT {attribute('e')} AS a, size, v FROM (SELECT unnest(items) AS e, size, v FROM val)) JOIN wt ON k = size GROUP BY a),
ww AS (SELECT coalesce(sum(w * v), 0) AS s FROM val JOIN wt ON k = size),
x AS (SELECT ee.e, coalesce(p, 0) - (ww.s - coalesce(aa.s, 0)) AS x FROM ee CROSS JOIN ww LEFT JOIN pe ON pe.e = ee.e LEFT JOIN aa ON aa.a = {attribute('ee.e')})"""


X_OUT = f"SELECT {attribute('e')} AS attr, {value_of('e')} AS val, {rounded('x')} AS x FROM x"


def elements_sql(view: str) -> str:
    return f"WITH {view_ctes(view)} SELECT {attribute('e')} AS attr, {value_of('e')} AS val, sum(c)::BIGINT AS freq_cnt FROM el GROUP BY e"


def itemsets_sql(view: str) -> str:
    return f"WITH {itemset_ctes(view)} SELECT array_to_string(items, '|') AS items, size, cnt FROM its"


def rules_sql(view: str, score: str = "is") -> str:
    return f"""WITH {rule_ctes(view, score)}
SELECT array_to_string(lhs, '|') AS lhs, array_to_string(rhs, '|') AS rhs, cnt, lc AS lhs_cnt, hc AS rhs_cnt,
       {rounded('sup')} AS support, {rounded('conf')} AS confidence, {rounded('lift')} AS lift, {rounded('score')} AS score FROM rs"""


def values_sql(view: str, agg: str) -> str:
    return f"WITH {rule_ctes(view, agg=agg)} SELECT array_to_string(items, '|') AS items, n_rules, {rounded('v')} AS value FROM val"


def contribution_sql(view: str, form: str = "pruned", agg: str = "max", score: str = "is", keep: str = "TRUE", setting: Setting | None = None) -> str:
    body = pruned_ctes() if form == "pruned" else decomposed_ctes()
    return f"WITH {rule_ctes(view, score, agg, setting, keep=keep)}, {body} {X_OUT}"


def example_ctes(score: str) -> str:
    pick = {"printed": "floor(100 * (sup * lift) + 0.5)", "is_product": "sup * lift", "is": "sqrt(sup * lift)"}
    pair = {i: (a, v) for i, a, v in MEASURED}
    source, cols = VIEW_COLUMNS["conversations"]
    listed = lambda x: "[" + ", ".join(f"'{a}={v}'" for a, v in sorted((pair[i] for i in x), key="=".join)) + "]"
    met = lambda x: "count(*) FILTER (WHERE " + " AND ".join(f"{a} = '{v}'" for a, v in (pair[i] for i in x)) + ")"
    rows = [
        f"SELECT {listed(lhs + rhs)} AS items, {len(lhs + rhs)} AS size, {listed(lhs)} AS lhs, {listed(rhs)} AS rhs, "
        f"{met(lhs + rhs)} AS cnt, {met(lhs)} AS lc, {met(rhs)} AS hc, count(*) AS n FROM v"
        for lhs, rhs, *_ in RULES
    ]
    return f"""v AS (SELECT {', '.join(f'{e} AS {n}' for n, e in cols.items())} FROM {source}),
rc AS ({' UNION ALL '.join(rows)}),
rm AS (SELECT *, cnt::DOUBLE / n AS sup, (cnt::DOUBLE * n) / (lc::DOUBLE * hc) AS lift FROM rc WHERE cnt > 0),
rs AS (SELECT *, ({pick[score]})::DOUBLE AS score FROM rm)"""


def example_sql(score: str) -> str:
    """Every valid coalition of the example, enumerated."""
    return f"""WITH {example_ctes(score)}, {value_ctes('max')},
el AS (SELECT list(e ORDER BY e) AS all_e FROM ee),
ss AS (SELECT list_filter(all_e, lambda y, i: ((m >> (i - 1)::INT) & 1) = 1) AS items FROM (SELECT all_e, unnest(range(0, 1 << len(all_e)::INT)) AS m FROM el)),
pr AS (SELECT e, items FROM ss, ee
  WHERE len(list_distinct(list_transform(items, lambda y: {attribute('y')}))) = len(items)
    AND len(list_filter(items, lambda y: {attribute('y')} = {attribute('e')})) = 0),
x AS (SELECT e, sum(w * (coalesce(v1.v, 0) - coalesce(v0.v, 0))) AS x, count(*) AS n FROM pr JOIN wt ON wt.k = len(pr.items)
  LEFT JOIN val v0 ON v0.items = pr.items LEFT JOIN val v1 ON v1.items = list_sort(list_append(pr.items, e)) GROUP BY e)
{X_OUT}"""


def naive_count_sql(view: str) -> str:
    a = attribute("e")
    return f"""WITH {rule_ctes(view)},
sz AS (SELECT {a} AS a, count(*) AS k FROM ee GROUP BY 1)
SELECT {attribute('ee.e')} AS attr, {value_of('ee.e')} AS val,
       round(exp(sum(CASE WHEN sz.a = {attribute('ee.e')} THEN 0 ELSE ln(sz.k + 1) END)))::BIGINT AS naive
FROM ee, sz GROUP BY ee.e"""


def pruned_count_sql(view: str) -> str:
    return f"""WITH {rule_ctes(view)}, {pruned_ctes()}
SELECT {attribute('e')} AS attr, {value_of('e')} AS val, count(DISTINCT items)::BIGINT AS pruned FROM pr GROUP BY e"""


def bound_sql(view: str) -> str:
    return f"""WITH {rule_ctes(view)}
SELECT {attribute('e')} AS attr, {value_of('e')} AS val,
       sum(CASE WHEN len(list_filter(items, lambda y: {attribute('y')} = {attribute('e')})) > 0 THEN 1 ELSE (SELECT max(size) FROM rs) + 1 END)::BIGINT AS bound
FROM ee, rs GROUP BY e"""


def i_top_sql(view: str) -> str:
    return f"""WITH {rule_ctes(view)}
SELECT {attribute('e')} AS attr, {value_of('e')} AS val, {rounded('max(score)')} AS x FROM ee JOIN rs ON list_contains(items, e) GROUP BY e"""


def influence_ctes(agg: str) -> str:
    return f"""xi AS (SELECT e, (SELECT {AGGS[agg]} FROM rs) - coalesce((SELECT {AGGS[agg]} FROM rs WHERE NOT list_contains(items, ee.e)), 0) AS x FROM ee)"""


def influence_sql(view: str, agg: str) -> str:
    return f"""WITH {rule_ctes(view)}, {influence_ctes(agg)}
SELECT {attribute('e')} AS attr, {value_of('e')} AS val, {rounded('x')} AS x FROM xi"""


def nx_ctes() -> str:
    return f"""{pruned_ctes()},
nx AS (SELECT x.e, x.x, fe.cnt, rank() OVER (ORDER BY round(x.x, 9) DESC) AS rank_x, rank() OVER (ORDER BY fe.cnt DESC) AS rank_freq FROM x JOIN fe USING (e)),
nz AS (SELECT *, rank_freq::DOUBLE / rank_x AS nx FROM nx)"""


def bands_ctes() -> str:
    return """bd AS (SELECT *, least(floor((score - lo) * 3 / (hi - lo)), 2)::INT AS band FROM rs, (SELECT min(score) AS lo, max(score) AS hi FROM rs)),
bn AS (SELECT e, sum((band = 0)::INT)::BIGINT AS band0, sum((band = 1)::INT)::BIGINT AS band1, sum((band = 2)::INT)::BIGINT AS band2
       FROM (SELECT unnest(items) AS e, band FROM bd) GROUP BY e),
bs AS (SELECT sum((band = 0)::INT) AS s0, sum((band = 1)::INT) AS s1, sum((band = 2)::INT) AS s2 FROM bd)"""


def importance_sql(view: str) -> str:
    share = lambda i: f"{rounded(f'coalesce(band{i}, 0)::DOUBLE / greatest(s{i}, 1)')} AS share{i}"
    return f"""WITH {rule_ctes(view)}, {pruned_ctes()}, {bands_ctes()}
SELECT {attribute('x.e')} AS attr, {value_of('x.e')} AS val, {rounded('x.x')} AS x, fe.cnt AS freq_cnt,
       coalesce(band0, 0) AS band0, coalesce(band1, 0) AS band1, coalesce(band2, 0) AS band2, {share(0)}, {share(1)}, {share(2)}
FROM x JOIN fe USING (e) LEFT JOIN bn USING (e), bs"""


def is_bands_sql(view: str) -> str:
    return f"WITH {rule_ctes(view)}, {bands_ctes()} SELECT band, count(*) AS n_rules, {rounded('min(score)')} AS lo, {rounded('max(score)')} AS hi FROM bd GROUP BY band"


def normalized_sql(view: str) -> str:
    return f"""WITH {rule_ctes(view)}, {nx_ctes()}
SELECT {attribute('e')} AS attr, {value_of('e')} AS val, rank_x::INT AS rank_x, rank_freq::INT AS rank_freq, {rounded('nx')} AS nx FROM nz"""


def rx_ctes() -> str:
    return f"""{nx_ctes()},
rx AS (SELECT lhs, rhs, score, size, min(nx) AS rx, arg_min(e, (nx, e)) AS weakest
       FROM (SELECT lhs, rhs, score, size, unnest(items) AS e FROM rs) JOIN nz USING (e) GROUP BY lhs, rhs, score, size)"""


def rule_importance_sql(view: str) -> str:
    return f"""WITH {rule_ctes(view)}, {rx_ctes()}
SELECT array_to_string(lhs, '|') AS lhs, array_to_string(rhs, '|') AS rhs, {rounded('rx')} AS rx, weakest FROM rx"""


def redundant_filter_sql(view: str, t: float) -> str:
    return f"""WITH {rule_ctes(view)}, {rx_ctes()}
SELECT sum((rx <= {t})::INT)::BIGINT AS removed, sum((rx > {t})::INT)::BIGINT AS kept, {rounded(f'avg((rx <= {t})::INT)')} AS removed_share FROM rx"""


def redundant_pairs_sql(view: str, eps: float) -> str:
    return f"""WITH {rule_ctes(view)}, {rx_ctes()},
lg AS (SELECT *, list_filter(lhs, lambda y: y <> weakest) AS l, list_filter(rhs, lambda y: y <> weakest) AS r FROM rx WHERE size >= 3)
SELECT array_to_string(lg.lhs, '|') AS long_lhs, array_to_string(lg.rhs, '|') AS long_rhs, weakest,
       {rounded('lg.score')} AS long_score, {rounded('rs.score')} AS short_score
FROM lg JOIN rs ON rs.lhs = l AND rs.rhs = r WHERE len(l) > 0 AND len(r) > 0 AND rs.score >= (1 - {eps}::DOUBLE) * lg.score"""


def attribute_importance_sql(view: str) -> str:
    return f"WITH {rule_ctes(view)}, {nx_ctes()} SELECT {attribute('e')} AS attr, {rounded('avg(nx)')} AS ax, count(*) AS n_elems FROM nz GROUP BY 1"


def attribute_profile_sql(view: str) -> str:
    a = attribute("e")
    return f"""WITH {rule_ctes(view)}, {nx_ctes()}
SELECT {a} AS attr, {value_of('e')} AS val, {rounded('nx')} AS nx, {rounded(f'cnt::DOUBLE / sum(cnt) OVER (PARTITION BY {a})')} AS share FROM nz"""


def _average_rank(c: str) -> str:
    return f"(rank() OVER (ORDER BY round({c}, 9)) + (count(*) OVER (PARTITION BY round({c}, 9)) - 1) / 2.0)"


def spearman_select(a: str, b: str) -> str:
    """SELECT of the rank correlation of two CTEs (e, x)."""
    return f"""SELECT corr(ra, rb) FROM (SELECT {_average_rank('a.x')} AS ra, {_average_rank('b.x')} AS rb FROM {a} a JOIN {b} b USING (e))"""


def itop_ctes() -> str:
    return "xt AS (SELECT e, max(score) AS x FROM ee JOIN rs ON list_contains(items, e) GROUP BY e)"


def quality_sql(view: str, what: str) -> str:
    """Influence (sum) against exact scores: p_at_10, ap_at_10 or a rank correlation."""
    base = f"WITH {rule_ctes(view)}, {pruned_ctes()}, {influence_ctes('sum')}, {itop_ctes()}"
    rank = lambda t: f"(SELECT e, row_number() OVER (ORDER BY round(x, 9) DESC, e) AS r FROM {t})"
    both = f"SELECT greatest(a.r, b.r) AS r FROM {rank('x')} a JOIN {rank('xi')} b USING (e)"
    if what == "p_at_10":
        return f"{base} SELECT {rounded('count(*) / 10.0::DOUBLE')} AS p FROM ({both}) WHERE r <= 10"
    if what == "ap_at_10":
        return f"{base} SELECT {rounded('sum(1.0::DOUBLE * hits / k) / 10')} AS ap FROM (SELECT k, count(r) AS hits FROM (SELECT unnest(range(1, 11)) AS k) LEFT JOIN ({both}) ON r <= k GROUP BY k)"
    other = {"spearman_influence": "xi", "spearman_itop": "xt"}[what]
    return f"{base} SELECT {rounded(f'({spearman_select("x", other)})')} AS rho"


def properties_sql(view: str) -> str:
    return f"""WITH {rule_ctes(view)}
SELECT '{view}' AS run_id, count(*) AS n_rules, {rounded('avg(size)')} AS avg_length, max(size) AS max_length, (SELECT n FROM en) AS n_elements FROM rs"""


def speedup_sql(view: str) -> str:
    return f"""WITH {rule_ctes(view)}
SELECT n AS n_elements, t AS tau, {rounded('n * t * (t + 1)::DOUBLE / (n * (t + 1) + t * t)')} AS speedup FROM (SELECT (SELECT n FROM en) AS n, max(size) AS t FROM rs)"""


def window_counts_sql(days: int) -> str:
    cols = ", ".join(f"{e} AS {c}" for c, e in EVENT_COLUMNS.items())
    return f"""SELECT strftime(w, '%Y-%m-%d') AS start, et, h, dow, v, u, k, count(*) AS c
FROM (SELECT time_bucket(INTERVAL '{days} days', ts, TIMESTAMP '1970-01-01') AS w, {cols} FROM events) GROUP BY ALL"""


def windows_contribution_sql(days: int, setting: Setting) -> str:
    """Every window mined and scored on its own rows; over pruned coalitions, the window ``g`` in every key."""
    cols = ", ".join(f'{e} AS "{c}"' for c, e in EVENT_COLUMNS.items())
    parts = " UNION ALL ".join(f"SELECT g, rid, c, '{c}=' || \"{c}\" AS e FROM t WHERE \"{c}\" IS NOT NULL" for c in EVENT_COLUMNS)
    pct = round(setting.min_support * 100)
    attr = attribute
    return f"""WITH v AS (SELECT time_bucket(INTERVAL '{days} days', ts, TIMESTAMP '1970-01-01') AS g, {cols} FROM events),
t AS (SELECT row_number() OVER () AS rid, * FROM (SELECT *, count(*) AS c FROM v GROUP BY ALL)),
nn AS (SELECT g, sum(c)::BIGINT AS n FROM t GROUP BY g),
el AS ({parts}),
fe AS (SELECT g, e FROM el JOIN nn USING (g) GROUP BY g, e, n HAVING sum(c) * 100 >= {pct} * n),
fel AS (SELECT g, rid, c, e FROM el SEMI JOIN fe USING (g, e)),
{level_ctes(setting.max_len, 'g', f'sum(c) * 100 >= {pct} * any_value(n)')},
its AS (SELECT * FROM i_all),
sp AS (SELECT g, items, size, cnt, n, unnest(range(1, (1 << size) - 1)) AS m FROM its WHERE size >= 2),
sd AS (SELECT *, list_filter(items, lambda x, i: ((m >> (i - 1)::INT) & 1) = 1) AS lhs,
              list_filter(items, lambda x, i: ((m >> (i - 1)::INT) & 1) = 0) AS rhs FROM sp),
rc AS (SELECT sd.*, l.cnt AS lc, h.cnt AS hc FROM sd JOIN its l ON l.g = sd.g AND l.items = lhs JOIN its h ON h.g = sd.g AND h.items = rhs),
rm AS (SELECT *, cnt::DOUBLE / n AS sup, (cnt::DOUBLE * n) / (lc::DOUBLE * hc) AS lift FROM rc),
rs AS (SELECT *, sqrt(sup * lift) AS score FROM rm WHERE greatest(lift, 1 / lift) >= {setting.min_lift}),
val AS (SELECT g, items, size, max(score) AS v FROM rs GROUP BY g, items, size),
ee AS (SELECT DISTINCT g, unnest(items) AS e FROM val),
en AS (SELECT g, count(*) AS n FROM ee GROUP BY g),
wt AS (SELECT g, k, 1.0::DOUBLE / (n * coalesce(list_aggregate(list_transform(range(1, k + 1), lambda i: (n - i)::DOUBLE / i), 'product'), 1.0)) AS w
       FROM en, (SELECT unnest(range(0, 12)) AS k) WHERE k < n),
co AS (SELECT g, items FROM val UNION SELECT g, list_filter(items, lambda y, i: i <> j) FROM val, (SELECT unnest(range(1, 12)) AS j) WHERE j <= size),
pr AS (SELECT co.g, e, co.items FROM co JOIN ee USING (g) WHERE len(list_filter(co.items, lambda y: {attr('y')} = {attr('e')})) = 0),
x AS (SELECT pr.g, e, sum(w * (coalesce(v1.v, 0) - coalesce(v0.v, 0))) AS x FROM pr
      JOIN wt ON wt.g = pr.g AND wt.k = len(pr.items) LEFT JOIN val v0 ON v0.g = pr.g AND v0.items = pr.items
      LEFT JOIN val v1 ON v1.g = pr.g AND v1.items = list_sort(list_append(pr.items, e)) GROUP BY pr.g, e)
SELECT strftime(g, '%Y-%m-%d') AS window_start, {attr('e')} AS attr, {value_of('e')} AS val, {rounded('x')} AS x FROM x"""


# --- preparation


def sample_sql(table: str, key: str, n: int) -> str:
    return f"SELECT {key} FROM {table} ORDER BY md5('0|' || {key}) LIMIT {n}"


def equal_width(c: str, lo: str, hi: str, bins: int) -> str:
    """Number of the bin of a double, by the cuts between lo and hi."""
    steps = " + ".join(f"({c} >= {lo} + ({hi} - {lo}) * {i} / {bins})::INT" for i in range(1, bins))
    return f"CASE WHEN {c} IS NULL THEN NULL WHEN {lo} = {hi} THEN 0 ELSE {steps} END"


def bins_sql(table: str, column: str, lo_hi: str, cell: str) -> str:
    return f"SELECT ({cell})::VARCHAR AS bin, count(*) AS n FROM (SELECT {column}::DOUBLE AS x FROM {table}), ({lo_hi}) GROUP BY 1"


def equal_width_sql(table: str, column: str, bins: int) -> str:
    edges = f"SELECT min({column})::DOUBLE AS lo, max({column})::DOUBLE AS hi FROM {table}"
    return bins_sql(table, column, edges, equal_width("x", "lo", "hi", bins))


def equal_depth_sql(table: str, column: str, bins: int) -> str:
    """Exact quantiles between rows; equal cuts count once."""
    shares = ", ".join(f"{i}.0 / {bins}" for i in range(1, bins))
    edges = f"SELECT list_distinct(quantile_cont({column}::DOUBLE, [{shares}])) AS cuts FROM {table}"
    return bins_sql(table, column, edges, "len(list_filter(cuts, lambda c: x >= c))")


def top_values_sql(table: str, column: str, k: int) -> str:
    top = f"SELECT {column} AS v FROM {table} WHERE {column} IS NOT NULL GROUP BY 1 ORDER BY count(*) DESC, 1 LIMIT {k}"
    return f"SELECT CASE WHEN {column} IN ({top}) THEN {column}::VARCHAR ELSE 'other' END AS bin, count(*) AS n FROM {table} WHERE {column} IS NOT NULL GROUP BY 1"


def worst_case_sql(view: str) -> str:
    source, cols = VIEW_COLUMNS[view]
    return f"SELECT count(*) AS n_rows, {len(cols)} AS n_attributes, {rounded(f'{len(cols)} * log10(count(*))')} AS log10_worst FROM {source}"


# --- more uses of the scores


def top_rules_sql(view: str, m: int) -> str:
    return f"""WITH {rule_ctes(view)}
SELECT array_to_string(lhs, '|') AS lhs, array_to_string(rhs, '|') AS rhs, {rounded('score')} AS score FROM rs ORDER BY round(score, 9) DESC, lhs, rhs LIMIT {m}"""


def drop_attributes_sql(view: str, t: float) -> str:
    """Itemsets of the view without the attributes scored below t: those without their elements."""
    return f"""WITH {rule_ctes(view)}, {nx_ctes()},
low AS (SELECT {attribute('e')} AS a FROM nz GROUP BY 1 HAVING avg(nx) < {t})
SELECT array_to_string(items, '|') AS items, size, cnt FROM its
WHERE NOT EXISTS (SELECT 1 FROM low WHERE list_contains(list_transform(items, lambda y: {attribute('y')}), a))"""


def drop_elements_sql(view: str, eps: float) -> str:
    return f"""WITH {rule_ctes(view)}, {pruned_ctes()},
weak AS (SELECT coalesce(list(e), []) AS es FROM x WHERE abs(x) <= {eps})
SELECT array_to_string(lhs, '|') AS lhs, array_to_string(rhs, '|') AS rhs FROM rs, weak WHERE NOT list_has_any(items, es)"""


def restricted_sql(view: str, elements: str, form: str) -> str:
    """Scores within the elements of a condition on ``e``; rules with others are ignored. ``fe`` has those in no rule too."""
    body = pruned_ctes() if form == "pruned" else decomposed_ctes()
    base = rule_ctes(view).split(",\nval AS")[0]
    return f"""WITH {base},
within AS (SELECT list(e) AS es FROM fe WHERE {elements}),
val AS (SELECT items, size, count(*) AS n_rules, max(score) AS v FROM rs, within WHERE list_has_all(es, items) GROUP BY items, size),
ee AS (SELECT e FROM fe WHERE {elements}),
{weight_ctes()}, {body} {X_OUT}"""


def interaction_sql(view: str, element: str, attr: str) -> str:
    """The element's score among the rules that hold each value of the attribute, one value after the other."""
    base = rule_ctes(view).split(",\nval AS")[0]
    return f"""WITH {base},
gv AS (SELECT e AS given FROM fe WHERE {attribute('e')} = '{attr}'),
val AS (SELECT given, items, size, max(score) AS v FROM rs, gv WHERE list_contains(items, given) GROUP BY given, items, size),
ee AS (SELECT DISTINCT given, unnest(items) AS e FROM val),
en AS (SELECT given, count(*) AS n FROM ee GROUP BY given),
wv AS (SELECT val.*, n, 1.0::DOUBLE / (n * coalesce(list_aggregate(list_transform(range(1, size), lambda i: (n - i)::DOUBLE / i), 'product'), 1.0)) AS w_in,
       CASE WHEN size < n THEN 1.0::DOUBLE / (n * list_aggregate(list_transform(range(1, size + 1), lambda i: (n - i)::DOUBLE / i), 'product')) ELSE 0 END AS w_out
       FROM val JOIN en USING (given)),
xg AS (SELECT given, sum(CASE WHEN list_contains(items, '{element}') THEN w_in * v
                             WHEN NOT list_contains(list_transform(items, lambda y: {attribute('y')}), '{element.split("=")[0]}') THEN -w_out * v ELSE 0 END) AS x
       FROM wv GROUP BY given)
SELECT {value_of('given')} AS given, {rounded('x')} AS x FROM xg SEMI JOIN (SELECT given FROM ee WHERE e = '{element}') USING (given)"""


def subset_sql(view: str, elements: list[str]) -> str:
    """Summed scores of a group, and its score as one player, enumerated over the coalitions that lack its attributes."""
    listed = ", ".join(f"'{e}'" for e in sorted(elements))
    attrs = ", ".join(f"'{e.split('=')[0]}'" for e in elements)
    k = len(elements)
    return f"""WITH {rule_ctes(view)}, {pruned_ctes()},
ge AS (SELECT [{listed}] AS ge, [{attrs}] AS ga),
gc AS (SELECT items AS s FROM val, ge WHERE NOT list_has_any(list_transform(items, lambda y: {attribute('y')}), ga)
       UNION SELECT list_filter(items, lambda y: NOT list_contains(ge, y)) FROM val, ge WHERE list_has_all(items, ge)),
gw AS (SELECT k, 1.0::DOUBLE / (n * coalesce(list_aggregate(list_transform(range(1, k + 1), lambda i: (n - i)::DOUBLE / i), 'product'), 1.0)) AS w
       FROM (SELECT n - {k - 1} AS n FROM en), (SELECT unnest(range(0, 12)) AS k) WHERE k < n),
u AS (SELECT sum(w * (coalesce(v1.v, 0) - coalesce(v0.v, 0))) AS x FROM gc JOIN gw ON k = len(s), ge
      LEFT JOIN val v0 ON v0.items = s LEFT JOIN val v1 ON v1.items = list_sort(list_concat(s, ge)))
SELECT {rounded(f'(SELECT sum(x) FROM x WHERE e IN ({listed}))')} AS summed, {rounded('u.x')} AS as_one FROM u"""


def score_correlation_sql(view: str) -> str:
    return f"WITH {rule_ctes(view)}, {pruned_ctes()} SELECT {rounded('corr(x.x, fe.cnt)')} AS corr FROM x JOIN fe USING (e)"


def score_error_sql(view: str) -> str:
    return f"""WITH {rule_ctes(view)}, {pruned_ctes()}, {influence_ctes('sum')}
SELECT {rounded('max(abs(x.x - xi.x))')} AS max_error, {rounded('avg(abs(x.x - xi.x))')} AS mean_error, {rounded('max(abs(x.x - xi.x)) / max(abs(x.x))')} AS relative_error
FROM x JOIN xi USING (e)"""


def near_sql(view: str) -> str:
    """Exact scores; the engine's estimates are to be near all of them."""
    return f"WITH {rule_ctes(view)}, {pruned_ctes()} SELECT {attribute('e')} AS attr, {value_of('e')} AS val, {rounded('x')} AS x, TRUE AS near FROM x"


def robustness_sql(view: str) -> str:
    """Rank correlations of other scores and aggregates with IS and max, each variant's scores on their own."""
    base = rule_ctes(view).split(",\nval AS")[0]
    variants = {"score_confidence": ("conf", "max"), "score_lift": ("lift", "max")} | {f"agg_{a}": ("score", a) for a in ("sum", "top2", "top3", "avg")}
    cells = [("reference", AGGS["max"])] + [(n, AGGS[a].replace("score", c)) for n, (c, a) in variants.items()]
    parts = " UNION ALL ".join(f"SELECT '{n}' AS variant, items, size, {e} AS v FROM rs GROUP BY items, size" for n, e in cells)
    return f"""WITH {base},
vv AS ({parts}),
ee AS (SELECT DISTINCT unnest(items) AS e FROM vv), {weight_ctes()},
{variant_scores('vv', ['variant'], 'ee', 'wt')},
rk AS (SELECT r.e, x.variant, {_grouped_rank('r.x', 'x.variant')} AS ra, {_grouped_rank('x.x', 'x.variant')} AS rb
       FROM xs x JOIN xs r ON r.e = x.e AND r.variant = 'reference' WHERE x.variant <> 'reference')
SELECT variant, {rounded('CASE WHEN count(DISTINCT ra) > 1 AND count(DISTINCT rb) > 1 THEN corr(ra, rb) END')} AS rank_corr FROM rk GROUP BY variant"""


def _grouped_rank(c: str, by: str) -> str:
    return f"(rank() OVER (PARTITION BY {by} ORDER BY round({c}, 9)) + (count(*) OVER (PARTITION BY {by}, round({c}, 9)) - 1) / 2.0)"


def variant_scores(values: str, keys: list[str], elements: str, weights: str) -> str:
    """xs (keys, e, x): decomposed scores for each key of ``values`` (keys, items, size, v).

    ``elements`` (and ``weights``) hold e (k, w) for all keys, or for their first key.
    """
    k, on = ", ".join(keys), keys[0]
    shared = "g" in keys
    using = f"USING ({on})" if shared else "ON TRUE"
    same = f"wt.{on} = v.{on} AND " if shared else ""
    return f"""ve AS (SELECT v.*, win.w AS w_in, coalesce(wout.w, 0) AS w_out FROM {values} v
   JOIN {weights} win ON {same.replace('wt.', 'win.')}win.k = v.size - 1 LEFT JOIN {weights} wout ON {same.replace('wt.', 'wout.')}wout.k = v.size),
vp AS (SELECT {k}, e, sum(p) AS p FROM (SELECT {k}, unnest(items) AS e, w_in * v AS p FROM ve) GROUP BY {k}, e),
va AS (SELECT {k}, a, sum(s) AS s FROM (SELECT {k}, {attribute('e')} AS a, s FROM (SELECT {k}, unnest(items) AS e, w_out * v AS s FROM ve)) GROUP BY {k}, a),
vw AS (SELECT {k}, sum(w_out * v) AS s FROM ve GROUP BY {k}),
xs AS (SELECT vw.*, el.e, coalesce(vp.p, 0) - (vw.s - coalesce(va.s, 0)) AS x FROM vw JOIN {elements} el {using}
   LEFT JOIN vp ON {' AND '.join(f'vp.{c} = vw.{c}' for c in keys)} AND vp.e = el.e
   LEFT JOIN va ON {' AND '.join(f'va.{c} = vw.{c}' for c in keys)} AND va.a = {attribute('el.e')})"""


# --- windows


def sliding_sql(days: int, step: int) -> str:
    cols = ", ".join(f"{e} AS {c}" for c, e in EVENT_COLUMNS.items())
    return f"""SELECT strftime(w + INTERVAL (j * {step}) DAYS, '%Y-%m-%d') AS start, et, h, dow, v, u, k, count(*) AS c
FROM (SELECT time_bucket(INTERVAL '{step} days', ts, TIMESTAMP '1970-01-01') AS w, {cols} FROM events), (SELECT unnest(range({1 - days // step}, 1)) AS j) GROUP BY ALL"""


def session_sql(gap_hours: int) -> str:
    cols = ", ".join(f"{e} AS {c}" for c, e in EVENT_COLUMNS.items())
    names = ", ".join(EVENT_COLUMNS)
    return f"""WITH e AS (SELECT ts, {cols} FROM events),
f AS (SELECT *, CASE WHEN lag(ts) OVER w + INTERVAL '{gap_hours} hours' >= ts THEN 0 ELSE 1 END AS fresh FROM e WINDOW w AS (PARTITION BY {names} ORDER BY ts)),
n AS (SELECT *, sum(fresh) OVER (PARTITION BY {names} ORDER BY ts ROWS UNBOUNDED PRECEDING) AS s FROM f)
SELECT strftime(min(ts), '%Y-%m-%d %H:%M:%S') AS start, {names}, count(*) AS c FROM n GROUP BY {names}, s"""


# --- the evaluation set

RAW_COLUMNS: dict[str, tuple[str, list[str], dict[str, str], dict[str, str]]] = {
    "conversations": (
        "conversations",
        ["conv_id", "turn"],
        {"turn": "turn", "len": "length(text)"},
        {"role": "role", "qm": _has("text", "'?'"), "nl": _has("text", "chr(10)")},
    ),
    "documents": (
        "documents LEFT JOIN labels USING (doc_id)",
        ["doc_id"],
        {"nc": "n_chars"},
        {c: VIEW_COLUMNS["documents"][1][c] for c in ("lang", "source", "q", "t", "hu", "em", "pi")},
    ),
    "events": (
        "events",
        ["event_id"],
        {"v": "value", "u": "user_id", "k": "regexp_extract(props, '\"k\": *([0-9]+)', 1)::INT", "h": "hour(ts)"},
        {"et": "event_type", "dow": EVENT_COLUMNS["dow"]},
    ),
    "pages": ("pages", ["page_id"], {"len": "length(html)"}, {c: VIEW_COLUMNS["pages"][1][c] for c in ("sch", "hl", "tb", "sc", "nav")}),
    "embeddings": ("embeddings", ["vec_id"], {f"x{i}": f"embedding[{i}]" for i in range(1, 9)}, {"lab": "label::VARCHAR"}),
    "star": (
        VIEW_COLUMNS["star"][0],
        ["l_orderkey", "l_linenumber"],
        {"q": "l_quantity", "ep": "l_extendedprice", "ps": "p_size", "pr": "p_retailprice"},
        {c: VIEW_COLUMNS["star"][1][c] for c in ("rf", "ls", "os", "seg", "reg", "nat", "pt")},
    ),
}


def grid_ctes(instances: list[Instance]) -> str:
    """rs: scored rules of all instances, ``g`` the run id; itemsets level by level at each base's lowest support."""
    ctes, bases = [], []
    for view, n in dict.fromkeys((i.view, i.sample_rows) for i in instances):
        source, key, numeric, plain = RAW_COLUMNS[view]
        picked = ", ".join([f'({e})::DOUBLE AS "{c}"' for c, e in numeric.items()] + [f'{e} AS "{c}"' for c, e in plain.items()])
        joined = " || '|' || ".join(key)
        name = f"{view}_{n}"
        ctes.append(f"r_{name} AS MATERIALIZED (SELECT {picked} FROM {source} ORDER BY md5('0|' || {joined}), {', '.join(key)} LIMIT {n})")
        edges = ", ".join(f'min("{c}") AS "{c}_lo", max("{c}") AS "{c}_hi"' for c in numeric)
        ctes.append(f"q_{name} AS (SELECT {edges} FROM r_{name})")
        for b in dict.fromkeys(i.n_bins for i in instances if (i.view, i.sample_rows) == (view, n)):
            cells = [f"'{c}=' || (" + equal_width(f'"{c}"', f'"{c}_lo"', f'"{c}_hi"', b) + ")" for c in numeric] + [f"'{c}=' || \"{c}\"" for c in plain]
            bases.append(f"SELECT '{view}-r{n}-b{b}' AS g, list_sort(list_filter([{', '.join(cells)}], lambda y: y IS NOT NULL)) AS items FROM r_{name}, q_{name}")
    lowest = {i.base: min(round(j.min_support * 100) for j in instances if j.base == i.base) for i in instances}
    low = ", ".join(f"('{b}', {p})" for b, p in lowest.items())
    runs = ", ".join(f"('{i.base}', '{i.run_id}', '{i.view}', {round(i.min_support * 100)}, {i.min_lift}::DOUBLE)" for i in instances)
    width = max(len(RAW_COLUMNS[i.view][2]) + len(RAW_COLUMNS[i.view][3]) for i in instances)
    levels = level_ctes(width, "g", "sum(c) * 100 >= any_value(pct) * any_value(n)")
    return ",\n".join(ctes) + f""",
t AS MATERIALIZED (SELECT row_number() OVER () AS rid, * FROM (SELECT g, items, count(*) AS c FROM ({' UNION ALL '.join(bases)}) GROUP BY ALL)),
nn AS (SELECT g, n, pct FROM (SELECT g, sum(c)::BIGINT AS n FROM t GROUP BY g) JOIN (VALUES {low}) l(g, pct) USING (g)),
el AS (SELECT g, rid, c, unnest(items) AS e FROM t),
fe AS (SELECT g, e FROM el JOIN nn USING (g) GROUP BY g, e, n, pct HAVING sum(c) * 100 >= pct * n),
fel AS MATERIALIZED (SELECT g, rid, c, e FROM el SEMI JOIN fe USING (g, e)),
{levels},
its AS (SELECT * FROM i_all),
sp AS (SELECT *, unnest(range(1, (1 << size) - 1)) AS m FROM its WHERE size >= 2),
sd AS (SELECT *, list_filter(items, lambda x, i: ((m >> (i - 1)::INT) & 1) = 1) AS lhs, list_filter(items, lambda x, i: ((m >> (i - 1)::INT) & 1) = 0) AS rhs FROM sp),
rc AS (SELECT sd.*, l.cnt AS lc, h.cnt AS hc FROM sd JOIN its l ON l.g = sd.g AND l.items = lhs JOIN its h ON h.g = sd.g AND h.items = rhs),
rm AS (SELECT *, cnt::DOUBLE / n AS sup, cnt::DOUBLE / lc AS conf, (cnt::DOUBLE * n) / (lc::DOUBLE * hc) AS lift FROM rc),
rs AS MATERIALIZED (SELECT run AS g, view, items, size, lhs, rhs, conf, lift, sqrt(sup * lift) AS score
   FROM rm JOIN (VALUES {runs}) k(base, run, view, pct, least_lift) ON base = g WHERE cnt * 100 >= pct * n AND greatest(lift, 1 / lift) >= least_lift),
ee AS MATERIALIZED (SELECT DISTINCT g, unnest(items) AS e FROM rs),
en AS (SELECT g, count(*) AS n FROM ee GROUP BY g),
wt AS MATERIALIZED (SELECT g, k, 1.0::DOUBLE / (n * coalesce(list_aggregate(list_transform(range(1, k + 1), lambda i: (n - i)::DOUBLE / i), 'product'), 1.0)) AS w
       FROM en, (SELECT unnest(range(0, 13)) AS k) WHERE k < n),
pp AS (SELECT g, view, count(*) AS n_rules, avg(size) AS avg_length, max(size) AS max_length, any_value(n) AS n_elements FROM rs JOIN en USING (g) GROUP BY g, view)"""


def grid_properties_sql(instances: list[Instance]) -> str:
    edges = ", ".join(
        f"{rounded(f'{f}({c})') if c == 'avg_length' else f'{f}({c})'} AS {f}_{c}" for c in ("n_rules", "avg_length", "n_elements") for f in ("min", "max")
    )
    return f"WITH {grid_ctes(instances)} SELECT view, count(*) AS n_sets, {edges}, max(max_length) AS max_length FROM pp GROUP BY view"


def grid_coalitions_sql(instances: list[Instance], by: str) -> str:
    band = "view" if by == "view" else f"({' + '.join(f'({by} >= {cut})::INT' for cut in BANDS[by])})::VARCHAR"
    return f"""WITH {grid_ctes(instances)},
sz AS (SELECT g, {attribute('e')} AS a, (count(*) + 1)::DOUBLE AS k FROM ee GROUP BY ALL),
nv AS (SELECT o.g, o.a, list_aggregate(list(i.k), 'product') AS naive FROM sz o JOIN sz i ON i.g = o.g AND i.a <> o.a GROUP BY o.g, o.a),
vs AS (SELECT DISTINCT g, items, size FROM rs),
co AS (SELECT g, items FROM vs UNION SELECT g, list_filter(items, lambda y, i: i <> j) FROM vs, (SELECT unnest(range(1, 13)) AS j) WHERE j <= size),
al AS (SELECT g, count(*) AS n FROM co GROUP BY g),
ha AS (SELECT g, a, count(*) AS n FROM (SELECT g, unnest(list_transform(items, lambda y: {attribute('y')})) AS a FROM co) GROUP BY ALL),
ct AS (SELECT ee.g, coalesce(naive, 1) AS naive, (al.n - coalesce(ha.n, 0)) AS pruned FROM ee JOIN al ON al.g = ee.g
   LEFT JOIN nv ON nv.g = ee.g AND nv.a = {attribute('ee.e')} LEFT JOIN ha ON ha.g = ee.g AND ha.a = {attribute('ee.e')})
SELECT {band} AS band, count(*) AS n, {rounded('avg(naive)')} AS avg_naive, {rounded('avg(pruned)')} AS avg_pruned, {rounded('avg(naive / pruned)')} AS avg_ratio
FROM ct JOIN pp USING (g) GROUP BY 1"""


def grid_robustness_sql(instances: list[Instance]) -> str:
    column = {"is": "score", "confidence": "conf", "lift": "lift"}
    cells = [(v, *v.split("_")) for v in ROBUSTNESS]
    parts = " UNION ALL ".join(f"SELECT g, '{v}' AS variant, items, size, {AGGS[a].replace('score', column[c])} AS v FROM rs GROUP BY g, items, size" for v, c, a in cells)
    return f"""WITH {grid_ctes(instances)},
vv AS MATERIALIZED ({parts}),
{variant_scores('vv', ['g', 'variant'], 'ee', 'wt')},
rk AS (SELECT x.g, x.variant, {_grouped_rank('r.x', 'x.g, x.variant')} AS ra, {_grouped_rank('x.x', 'x.g, x.variant')} AS rb
       FROM xs x JOIN xs r ON r.g = x.g AND r.e = x.e AND r.variant = '{ROBUSTNESS[0]}' WHERE x.variant <> '{ROBUSTNESS[0]}'),
rh AS (SELECT g, variant, CASE WHEN count(DISTINCT ra) > 1 AND count(DISTINCT rb) > 1 THEN corr(ra, rb) END AS rho FROM rk GROUP BY g, variant),
mc AS (SELECT variant, count(rho) AS n_sets, avg(rho) AS mean, 1.96 * coalesce(stddev_samp(rho), 0) / sqrt(count(rho)) AS half FROM rh GROUP BY variant)
SELECT variant, n_sets, {rounded('mean')} AS mean, {rounded('mean - half')} AS low, {rounded('mean + half')} AS high FROM mc"""


def grid_alternatives_sql(instances: list[Instance]) -> str:
    return f"""WITH {grid_ctes(instances)},
vv AS MATERIALIZED (SELECT g, 'exact' AS variant, items, size, max(score) AS v FROM rs GROUP BY g, items, size),
{variant_scores('vv', ['g', 'variant'], 'ee', 'wt')},
tp AS (SELECT g, max(score) AS top FROM rs GROUP BY g),
it AS (SELECT g, e, max(score) AS x FROM (SELECT g, unnest(items) AS e, score FROM rs) GROUP BY g, e),
fl AS (SELECT ee.g, ee.e, any_value(top) - coalesce(max(CASE WHEN NOT list_contains(items, ee.e) THEN score END), 0) AS x FROM ee JOIN tp USING (g) JOIN rs ON rs.g = ee.g GROUP BY ee.g, ee.e),
ls AS (SELECT 'i_top' AS method, * FROM it UNION ALL SELECT 'influence', * FROM fl),
rk AS (SELECT ls.g, method, greatest(row_number() OVER (PARTITION BY ls.g, method ORDER BY round(xs.x, 9) DESC, ls.e), row_number() OVER (PARTITION BY ls.g, method ORDER BY round(ls.x, 9) DESC, ls.e)) AS r,
   {_grouped_rank('xs.x', 'ls.g, method')} AS ra, {_grouped_rank('ls.x', 'ls.g, method')} AS rb FROM ls JOIN xs ON xs.g = ls.g AND xs.e = ls.e),
ql AS (SELECT g, method, count(*) FILTER (r <= 10) / 10.0::DOUBLE AS p,
   coalesce(sum(list_aggregate(list_transform(range(r, 11), lambda j: 1.0::DOUBLE / j), 'sum')) FILTER (r <= 10), 0) / 10 AS ap,
   CASE WHEN count(DISTINCT ra) > 1 AND count(DISTINCT rb) > 1 THEN corr(ra, rb) END AS rho FROM rk GROUP BY g, method)
SELECT method, count(*) AS n_sets, {rounded('avg(p)')} AS p_at_10, {rounded('avg(ap)')} AS ap_at_10, {rounded('avg(rho)')} AS rank_corr FROM ql GROUP BY method"""
