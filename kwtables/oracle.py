"""DuckDB counterparts of the queries: the graph, its paths and postings as unrolled joins, written apart from the engine."""

from __future__ import annotations

KIND = {"Region": 1, "Nation": 2, "Customer": 3, "Supplier": 4, "Part": 5, "Order": 6, "Lineitem": 7}
ROWS = {"Region": ("region", "r_regionkey", "r_name"), "Nation": ("nation", "n_nationkey", "n_name"), "Customer": ("customer", "c_custkey", "c_name"), "Supplier": ("supplier", "s_suppkey", "s_name"), "Part": ("part", "p_partkey", "p_name"), "Order": ("orders", "o_orderkey", "CAST(o_orderkey AS VARCHAR)"), "Lineitem": ("li", "l_key", "CAST(l_key AS VARCHAR)")}
LINKS = [("region", "nation", "Nation", "n_nationkey", "Region", "n_regionkey"), ("nation", "customer", "Customer", "c_custkey", "Nation", "c_nationkey"), ("nation", "supplier", "Supplier", "s_suppkey", "Nation", "s_nationkey"), ("customer", "orders", "Order", "o_orderkey", "Customer", "o_custkey"), ("order", "li", "Lineitem", "l_key", "Order", "l_orderkey"), ("part", "li", "Lineitem", "l_key", "Part", "l_partkey"), ("supplier", "li", "Lineitem", "l_key", "Supplier", "l_suppkey")]
BACK = [("lines", "li", "Order", "l_orderkey", "Lineitem", "l_key"), ("orders", "orders", "Customer", "o_custkey", "Order", "o_orderkey"), ("residents", "customer", "Nation", "c_nationkey", "Customer", "c_custkey"), ("nations", "nation", "Region", "n_regionkey", "Nation", "n_nationkey")]
TEXTS = [("market segment", "customer", "Customer", "c_custkey", "c_mktsegment"), ("brand", "part", "Part", "p_partkey", "p_brand"), ("part type", "part", "Part", "p_partkey", "p_type"), ("order priority", "orders", "Order", "o_orderkey", "o_orderpriority"), ("order status", "orders", "Order", "o_orderkey", "o_orderstatus"), ("return flag", "li", "Lineitem", "l_key", "l_returnflag"), ("line status", "li", "Lineitem", "l_key", "l_linestatus")]
TYPED = {"Part": "p_brand", "Order": "o_orderpriority", "Customer": "c_mktsegment"}
LI_ORDER = "l_discount, l_extendedprice, l_linenumber, l_linestatus, l_orderkey, l_partkey, l_quantity, l_returnflag, l_shipdate, l_suppkey, l_tax"
#: Scores in nine significant digits, as a number that grows with the score.
KEY = "CASE WHEN {0} > 0 THEN CAST(round((floor(log10({0})) * 9 + {0} / power(10.0::DOUBLE, floor(log10({0})))) * 1000000000) AS BIGINT) ELSE -1000000000000000000 END"
WORDS = "list_distinct(list_filter(string_split_regex(lower(coalesce({0}, '')), '[^a-z0-9]+'), lambda w: w <> ''))"


def words_of(column: str) -> str:
    return WORDS.format(column)


def graph(profile: str = "forward", scope: str = "occurrence", li_order: str = LI_ORDER) -> str:
    """CTEs li, nodes(id, type, text, lit, tok), edges(src, attr, dst)."""
    back = profile in ("linked", "many_types")
    typed = profile.startswith("many_types")
    links = LINKS + (BACK if back else [])
    attrs = sorted({x[0] for x in links} | {x[0] for x in TEXTS})
    ident = lambda kind, key: f"CAST({key} AS BIGINT) * 64 + {KIND[kind]}"
    rows = [f"SELECT {ident(k, key)} AS id, {f'coalesce({TYPED[k]}, {chr(39)}{k}{chr(39)})' if typed and k in TYPED else f'{chr(39)}{k}{chr(39)}'} AS type, {text} AS text, false AS lit FROM {t}" for k, (t, key, text) in ROWS.items()]
    values, arcs = [], [f"SELECT {ident(s, sk)} AS src, '{a}' AS attr, {ident(d, dk)} AS dst FROM {t}" for a, t, s, sk, d, dk in links]
    for a, t, s, sk, v in TEXTS:
        if scope == "occurrence":
            node = f"-(({ident(s, sk)}) * 64 + {attrs.index(a)})"
        else:
            shared = f"'{a}=' || {v}" if scope == "attribute" else v
            node = f"-CAST(hash({shared}) >> 4 AS BIGINT) - 1"
        values.append(f"SELECT {'' if scope == 'occurrence' else 'DISTINCT '}{node} AS id, 'Text' AS type, {v} AS text, true AS lit FROM {t} WHERE {v} IS NOT NULL")
        arcs.append(f"SELECT {ident(s, sk)} AS src, '{a}' AS attr, {node} AS dst FROM {t} WHERE {v} IS NOT NULL")
    union = " UNION ALL " if scope == "occurrence" else " UNION "
    return f"""li AS MATERIALIZED (SELECT *, l_orderkey * 65536 + row_number() OVER (PARTITION BY l_orderkey ORDER BY {li_order}) AS l_key FROM lineitem),
raw_nodes AS ({' UNION ALL '.join(rows)} UNION ALL SELECT * FROM ({union.join(values)})),
nodes AS MATERIALIZED (SELECT *, {words_of('text')} AS tok, CASE WHEN type = 'Text' THEN [] ELSE {words_of('type')} END AS type_tok, 1.0::DOUBLE AS pr FROM raw_nodes),
edges AS MATERIALIZED ({' UNION ALL '.join(arcs)})"""


def paths(d: int) -> str:
    """CTE paths(root, rtype, tail, nodes, arcs, labels, len, tail_pr, prev_pr, attr) over nodes and edges."""
    level = "SELECT id AS root, type AS rtype, id AS tail, [id] AS nodes, CAST([] AS VARCHAR[]) AS arcs, [type] AS labels, 1 AS len, pr AS tail_pr, CAST(NULL AS DOUBLE) AS prev_pr, CAST(NULL AS VARCHAR) AS attr FROM nodes"
    out = [f"path1 AS ({level})"]
    for n in range(2, d + 1):
        out.append(
            f"path{n} AS (SELECT p.root, p.rtype, e.dst AS tail, list_append(p.nodes, e.dst) AS nodes, list_append(p.arcs, e.src || '>' || e.attr || '>' || e.dst) AS arcs, list_append(list_append(p.labels, e.attr), v.type) AS labels, {n} AS len, v.pr AS tail_pr, p.tail_pr AS prev_pr, e.attr AS attr FROM path{n - 1} p JOIN edges e ON e.src = p.tail JOIN nodes v ON v.id = e.dst WHERE NOT list_contains(p.nodes, e.dst))"
        )
    return ",\n".join([*out, "paths AS (" + " UNION ALL ".join(f"SELECT * FROM path{n}" for n in range(1, d + 1)) + ")"])


def postings(words: list[str] | None) -> str:
    """CTE post(w, label, root, rtype, nodes, arcs, len, pr, sim); None: every word."""
    chosen = "" if words is None else " WHERE w IN (" + ", ".join(f"'{w}'" for w in words) + ")"
    return f"""hit AS (SELECT w, id, max(sim) AS sim FROM (SELECT unnest(tok) AS w, id, 1.0::DOUBLE / len(tok) AS sim FROM nodes UNION ALL SELECT unnest(type_tok) AS w, id, 1.0::DOUBLE / len(type_tok) AS sim FROM nodes){chosen} GROUP BY w, id),
attr_word AS (SELECT attr, w, sim FROM (SELECT attr, unnest({words_of('attr')}) AS w, 1.0::DOUBLE / len({words_of('attr')}) AS sim FROM (SELECT DISTINCT attr FROM edges)){chosen}),
post AS MATERIALIZED (SELECT w, array_to_string(labels, '.') AS label, false AS on_edge, root, rtype, nodes, arcs, len, tail_pr AS pr, sim FROM paths JOIN hit ON id = tail
  UNION ALL SELECT w, array_to_string(labels[:-2], '.') AS label, true AS on_edge, root, rtype, nodes, arcs, len, prev_pr AS pr, sim FROM paths JOIN attr_word USING (attr))"""


def index(profile: str, d: int, words: list[str] | None, scope: str = "occurrence") -> str:
    return f"WITH {graph(profile, scope)},\n{paths(d)},\n{postings(words)}"


def trees(words: list[str], validity: str = "tree", score: str = "pr * sim / len", source: str = "post") -> str:
    """CTE tree(root, rtype, l1.., h, score): one row for each subtree; len, pr and sim are sums over the words."""
    n = range(1, len(words) + 1)
    joins = " ".join(f"JOIN {source} t{i} ON t{i}.root = t1.root AND t{i}.w = '{words[i - 1]}'" for i in n if i > 1)
    arcs = "list_distinct(flatten([" + ", ".join(f"t{i}.arcs" for i in n) + "]))"
    valid = f" AND len({arcs}) = len(list_distinct(list_transform({arcs}, lambda a: string_split(a, '>')[3])))" if validity == "tree" else ""
    sums = ", ".join("(" + " + ".join(f"t{i}.{c}" for i in n) + f")::DOUBLE AS {c}" for c in ("len", "pr", "sim"))
    height = "greatest(" + ", ".join(f"t{i}.len" for i in n) + ")"
    return f"""combo AS (SELECT t1.root, t1.rtype, {', '.join(f't{i}.label AS l{i}' for i in n)}, {', '.join(f't{i}.nodes AS n{i}' for i in n)}, {height} AS h, {sums} FROM {source} t1 {joins} WHERE t1.w = '{words[0]}'{valid}),
tree AS (SELECT *, {score} AS score FROM combo)"""


def labels(words: list[str]) -> str:
    return ", ".join(f"l{i}" for i in range(1, len(words) + 1))


def joined_label(words: list[str]) -> str:
    return " || ' | ' || ".join(f"l{i}" for i in range(1, len(words) + 1))


AGGREGATE = {"sum": "sum(score)", "avg": "avg(score)", "max": "max(score)", "count": "CAST(count(*) AS DOUBLE)"}


def ranked(profile: str, d: int, words: list[str], k: int | None = 100, validity: str = "tree", agg: str = "sum", score: str = "pr * sim / len", prefix: str | None = None, scope: str = "occurrence") -> str:
    """The k best patterns: rank, label, height, n_trees, score."""
    ls = labels(words)
    limit = "" if k is None else f" WHERE rank <= {k}"
    return f"""{prefix or index(profile, d, words, scope)},
{trees(words, validity, score)},
pat AS (SELECT {ls}, max(h) AS h, count(*) AS n_trees, {AGGREGATE[agg]} AS score FROM tree GROUP BY {ls}),
placed AS (SELECT *, row_number() OVER (ORDER BY {KEY.format('score')} DESC, {ls}) AS rank FROM pat)
SELECT CAST(rank AS INTEGER) AS rank, {joined_label(words)} AS label, CAST(h AS INTEGER) AS height, CAST(n_trees AS BIGINT) AS n_trees, round(score, 6) AS score FROM placed{limit}"""
