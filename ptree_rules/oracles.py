"""DuckDB SQL for the registered queries. Encodings, itemsets and rules are built from a few parts; thresholds are integers."""

from __future__ import annotations

from itertools import combinations

#: The workloads' relations, as SQL over the given tables; all attributes are text.
RELATIONS = {
    "w1": """SELECT *, CASE WHEN rf = 'R' OR os = 'P' THEN 'c1' WHEN qty = 'hi' AND ls = 'O' THEN 'c4' WHEN qty = 'mid' THEN 'c3' ELSE 'c2' END AS class FROM (
        SELECT l_orderkey, l_linenumber, l_returnflag AS rf, l_linestatus AS ls, o_orderstatus AS os, CAST(year(o_orderdate) AS VARCHAR) AS oy,
               CASE WHEN l_quantity <= 16 THEN 'lo' WHEN l_quantity <= 33 THEN 'mid' ELSE 'hi' END AS qty,
               CASE WHEN l_discount < 0.035::DOUBLE THEN 'lo' WHEN l_discount < 0.065::DOUBLE THEN 'mid' ELSE 'hi' END AS disc
        FROM lineitem JOIN orders ON l_orderkey = o_orderkey)""",
    "w2": """SELECT lang, CASE WHEN n_chars < 500 THEN 's' WHEN n_chars < 2000 THEN 'm' ELSE 'l' END AS len_band,
               CAST(quality AS VARCHAR) AS quality, CAST(toxic AS VARCHAR) AS toxic,
               CASE WHEN regexp_matches(text, '[0-9]') THEN 'yes' ELSE 'no' END AS has_digit,
               CASE WHEN contains(text, '@') THEN 'yes' ELSE 'no' END AS has_at,
               CASE WHEN contains(text, 'http') THEN 'yes' ELSE 'no' END AS has_http,
               CASE WHEN contains(text, chr(10)) THEN 'yes' ELSE 'no' END AS has_newline,
               CASE WHEN contains(lower(text), 'license') THEN 'yes' ELSE 'no' END AS has_license
        FROM documents JOIN labels USING (doc_id)""",
    "w3": """SELECT r_name, c_mktsegment, o_orderpriority, o_orderstatus, l_returnflag, l_linestatus,
               CASE WHEN l_quantity <= 16 THEN 'lo' WHEN l_quantity <= 33 THEN 'mid' ELSE 'hi' END AS qty,
               CASE WHEN l_extendedprice < 35000 THEN 'lo' WHEN l_extendedprice < 70000 THEN 'mid' ELSE 'hi' END AS price,
               CASE WHEN l_discount < 0.05::DOUBLE THEN 'lo' ELSE 'hi' END AS disc2,
               CASE WHEN l_tax < 0.04::DOUBLE THEN 'lo' ELSE 'hi' END AS tax,
               CASE WHEN c_acctbal < 0 THEN 'neg' ELSE 'pos' END AS bal,
               CASE WHEN l_extendedprice * (1 - l_discount) >= 50000 THEN 'gt50' ELSE 'le50' END AS net_class
        FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey
        JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey""",
    "w4": """SELECT CASE WHEN A = 1 THEN 'yes' END AS A, CASE WHEN B = 1 THEN 'yes' END AS B, CASE WHEN C = 1 THEN 'yes' END AS C,
               CASE WHEN D = 1 THEN 'yes' END AS D, CASE WHEN E = 1 THEN 'yes' END AS E, CASE WHEN F = 1 THEN 'yes' END AS F, CASE WHEN G = 1 THEN 'yes' END AS G
        FROM (VALUES (1,1,0,0,0,0,0), (1,1,1,1,1,1,0), (0,1,0,1,0,0,1), (0,1,0,0,1,0,1), (0,0,0,1,0,1,1), (0,0,0,1,1,0,1), (0,1,0,0,1,0,0), (0,1,0,1,1,1,0)) t(A,B,C,D,E,F,G)""",
}
ATTRIBUTES = {
    "w1": ["rf", "ls", "os", "oy", "qty", "disc", "class"],
    "w2": ["lang", "len_band", "quality", "toxic", "has_digit", "has_at", "has_http", "has_newline", "has_license"],
    "w3": ["r_name", "c_mktsegment", "o_orderpriority", "o_orderstatus", "l_returnflag", "l_linestatus", "qty", "price", "disc2", "tax", "bal", "net_class"],
    "w4": list("ABCDEFG"),
}
PERCENT = {"w1": (10, 75), "w2": (35, 90), "w3": (17, 94), "w4": (10, 30)}
DECISION = {"w1": "class", "w2": "has_digit", "w3": "net_class", "w4": "G"}
#: Sizes of W3's itemsets end at four; grouping one size more shows it.
MOST = {"w1": 7, "w2": 9, "w3": 5, "w4": 7}


def counted(w: str, strict: bool = False, sizes: range | None = None, percent: int | None = None) -> str:
    """CTEs c (distinct rows with weights), n, f(k, label, cnt, parts): frequent itemsets by grouping sets over attribute subsets."""
    names = ATTRIBUTES[w]
    subsets = [s for k in sizes or range(1, MOST[w] + 1) for s in combinations(names, k)]
    sets = ", ".join(f"({', '.join(s)})" for s in subsets)
    cells = ", ".join(f"CASE WHEN grouping({a}) = 0 THEN '{a}=' || {a} END" for a in names)
    full = " AND ".join(f"(grouping({a}) = 1 OR {a} IS NOT NULL)" for a in names)
    percent = percent or PERCENT[w][0]
    return f"""c AS (SELECT {", ".join(names)}, count(*) AS weight FROM ({RELATIONS[w]}) GROUP BY ALL),
        n AS (SELECT CAST(sum(weight) AS BIGINT) AS n FROM c),
        g AS (SELECT list_sort(list_filter([{cells}], lambda x: x IS NOT NULL)) AS parts, CAST(sum(weight) AS BIGINT) AS cnt
              FROM c GROUP BY GROUPING SETS ({sets}) HAVING {full}),
        f AS (SELECT CAST(len(parts) AS INTEGER) AS k, array_to_string(parts, '|') AS label, cnt, parts FROM g, n WHERE cnt * 100 {">" if strict else ">="} {percent} * n)"""


def itemsets(w: str, where: str = "true", **how) -> str:
    return f"WITH {counted(w, **how)} SELECT k, label, cnt FROM f WHERE {where}"


#: Columns of a rule.
_RULE = "antecedent, consequent, k, cnt_xy, cnt_x, n, CAST(cnt_xy AS DOUBLE) / n AS support, CAST(cnt_xy AS DOUBLE) / cnt_x AS confidence, decision"


def rules(w: str, where: str = "true", confidence: int | None = None, select: str = _RULE, more: str = "", percent: int | None = None) -> str:
    """Strong rules with one item as consequent."""
    return f"""WITH {counted(w, percent=percent)},
        s AS (SELECT array_to_string(list_filter(parts, lambda x: x <> y), '|') AS antecedent, y AS consequent, CAST(k - 1 AS INTEGER) AS k, cnt AS cnt_xy
              FROM (SELECT parts, k, cnt, unnest(parts) AS y FROM f WHERE k > 1)),
        r AS (SELECT antecedent, consequent, s.k, cnt_xy, f.cnt AS cnt_x, n, split_part(consequent, '=', 1) AS decision
              FROM s JOIN f ON antecedent = label, n WHERE cnt_xy * 100 >= {confidence or PERCENT[w][1]} * f.cnt)
        {more} SELECT {select} FROM r WHERE {where}"""


def rules_any(w: str) -> str:
    return f"""WITH {counted(w)},
        m AS (SELECT parts, cnt, unnest(range(1, CAST(pow(2, k) AS BIGINT) - 1)) AS mask FROM f WHERE k > 1),
        s AS (SELECT list_filter(parts, lambda x, i: (mask >> (i - 1)) & 1 = 1) AS x, list_filter(parts, lambda x, i: (mask >> (i - 1)) & 1 = 0) AS y, cnt FROM m)
        SELECT array_to_string(x, '|') AS antecedent, array_to_string(y, '|') AS consequent, CAST(len(x) AS INTEGER) AS k, s.cnt AS cnt_xy, f.cnt AS cnt_x, n,
               CAST(s.cnt AS DOUBLE) / n AS support, CAST(s.cnt AS DOUBLE) / f.cnt AS confidence
        FROM s JOIN f ON array_to_string(x, '|') = label, n WHERE s.cnt * 100 >= {PERCENT[w][1]} * f.cnt"""


def dense() -> str:
    """CTE long(tid, label): order lines of W1 numbered by key and attributes, and their items."""
    names = ATTRIBUTES["w1"]
    cells = ", ".join(f"'{a}=' || {a}" for a in names)
    return f"""t AS (SELECT row_number() OVER (ORDER BY l_orderkey, l_linenumber, {", ".join(names)}) - 1 AS tid, * FROM ({RELATIONS["w1"]})),
        long AS (SELECT tid, unnest(list_filter([{cells}], lambda x: x IS NOT NULL)) AS label FROM t)"""
