"""DuckDB SQL that recomputes the graph queries from the given tables: edges are inlined, automata are written by hand."""

from __future__ import annotations

_ROOM = 10**14


def v(kind: int, key: str) -> str:
    return f"({kind} * {_ROOM} + CAST({key} AS BIGINT))"


def _names(value: str, table: str) -> str:
    return f"(SELECT value, dense_rank() OVER (ORDER BY value) AS k FROM (SELECT DISTINCT {value} AS value FROM {table}) WHERE value IS NOT NULL)"


def _named(kind: int, key: str, to: int, value: str, table: str) -> str:
    return f"SELECT {v(kind, key)} AS src, {v(to, 'n.k')} AS dst FROM {table} JOIN {_names(value, table)} n ON n.value = {value}"


def _lead(kind: int, key: str, table: str, group: str, order: str) -> str:
    return f"SELECT {v(kind, 'a')} AS src, {v(kind, 'b')} AS dst FROM (SELECT {key} AS a, lead({key}) OVER (PARTITION BY {group} ORDER BY {order}) AS b FROM {table}) WHERE b IS NOT NULL"


_HREF = """(SELECT DISTINCT page_id, unnest(regexp_extract_all(html, '<a href="(/[^"]*)"', 1)) AS href FROM pages)"""
_HOST = "(SELECT page_id, regexp_extract(url, '://([^/?#]*)', 1) AS host FROM pages WHERE regexp_extract(url, '://([^/?#]*)', 1) <> '')"
_NEXT = "(SELECT n_nationkey, coalesce(lead(n_nationkey) OVER (PARTITION BY n_regionkey ORDER BY n_nationkey), min(n_nationkey) OVER (PARTITION BY n_regionkey)) AS b FROM nation)"

#: src, dst of each label.
EDGES = {
    "bulk_supply": f"SELECT {v(4, 'l_suppkey')} AS src, {v(5, 'l_partkey')} AS dst FROM lineitem WHERE l_quantity >= 46",
    "sourced_from": f"SELECT {v(5, 'l_partkey')} AS src, {v(4, 'l_suppkey')} AS dst FROM lineitem WHERE l_quantity < 46",
    "located": f"""SELECT {v(7, 'l_orderkey * 8 + l_linenumber')} AS src, {v(2, 's_nationkey')} AS dst FROM lineitem JOIN supplier ON l_suppkey = s_suppkey
                   UNION ALL SELECT {v(4, 's_suppkey')}, {v(2, 's_nationkey')} FROM supplier
                   UNION ALL SELECT {v(6, 'o_orderkey')}, {v(2, 'c_nationkey')} FROM orders JOIN customer ON o_custkey = c_custkey""",
    "adjacent": f"SELECT {v(2, 'n_nationkey')} AS src, {v(2, 'b')} AS dst FROM {_NEXT}",
    "within": f"SELECT {v(2, 'n_nationkey')} AS src, {v(1, 'n_regionkey')} AS dst FROM nation",
    "ordered_by": f"SELECT {v(6, 'o_orderkey')} AS src, {v(3, 'o_custkey')} AS dst FROM orders",
    "resident_of": f"SELECT {v(3, 'c_custkey')} AS src, {v(2, 'c_nationkey')} AS dst FROM customer",
    "placed": f"SELECT {v(3, 'o_custkey')} AS src, {v(6, 'o_orderkey')} AS dst FROM orders",
    "has_item": f"SELECT {v(6, 'l_orderkey')} AS src, {v(7, 'l_orderkey * 8 + l_linenumber')} AS dst FROM lineitem",
    "of_part": f"SELECT {v(7, 'l_orderkey * 8 + l_linenumber')} AS src, {v(5, 'l_partkey')} AS dst FROM lineitem",
    "made_by": _named(5, "p_partkey", 20, "p_brand", "part"),
    "of_type": _named(5, "p_partkey", 21, "p_type", "part"),
    "succ_part": _lead(5, "p_partkey", "part", "p_brand", "p_partkey"),
    "follows": _lead(6, "o_orderkey", "orders", "o_custkey", "o_orderdate, o_orderkey"),
    "in_segment": _named(3, "c_custkey", 22, "c_mktsegment", "customer"),
    "has_priority": _named(6, "o_orderkey", 23, "o_orderpriority", "orders"),
    "acted": f"SELECT {v(8, 'user_id')} AS src, {v(9, 'event_id')} AS dst FROM events",
    "then": _lead(9, "event_id", "events", "user_id", "ts, event_id"),
    "event_kind": _named(9, "event_id", 10, "event_type", "events"),
    "is_customer": f"SELECT {v(8, 'c_custkey')} AS src, {v(3, 'c_custkey')} AS dst FROM customer WHERE c_custkey IN (SELECT user_id FROM events)",
    "reply": _lead(11, "conv_id * 1000 + turn", "conversations", "conv_id", "turn"),
    "links": f"SELECT {v(12, 'page_id')} AS src, {v(13, 'n.k')} AS dst FROM {_HREF} h JOIN {_names('href', _HREF)} n ON n.value = h.href",
    "on_host": f"SELECT {v(12, 'page_id')} AS src, {v(24, 'n.k')} AS dst FROM {_HOST} h JOIN {_names('host', _HOST)} n ON n.value = h.host",
    "from_source": _named(14, "doc_id", 15, "source", "documents"),
    "in_lang": _named(14, "doc_id", 16, "lang", "documents"),
    "same_text": f"""SELECT {v(14, 'doc_id')} AS src, {v(14, 'b')} AS dst FROM (SELECT doc_id, count(*) OVER (PARTITION BY md5(text)) AS n,
                     coalesce(lead(doc_id) OVER (PARTITION BY md5(text) ORDER BY doc_id), min(doc_id) OVER (PARTITION BY md5(text))) AS b FROM documents WHERE text IS NOT NULL) WHERE n > 1""",
    "quotes": f"SELECT {v(14, 'doc_id')} AS src, {v(19, 'item_id')} AS dst FROM documents d JOIN benchmark b ON contains(d.text, b.text)",
    "near": f"""SELECT {v(17, 'q')} AS src, {v(17, 'd')} AS dst FROM (SELECT a.vec_id AS q, b.vec_id AS d, row_number() OVER (PARTITION BY a.vec_id ORDER BY
                round(list_inner_product(CAST(a.embedding AS DOUBLE[]), CAST(b.embedding AS DOUBLE[])) / sqrt(list_inner_product(CAST(a.embedding AS DOUBLE[]), CAST(a.embedding AS DOUBLE[])))
                / sqrt(list_inner_product(CAST(b.embedding AS DOUBLE[]), CAST(b.embedding AS DOUBLE[]))), 6) DESC, b.vec_id) AS k FROM embeddings a JOIN embeddings b ON a.vec_id <> b.vec_id) WHERE k <= 3""",
    "in_class": f"SELECT {v(17, 'vec_id')} AS src, {v(18, 'label')} AS dst FROM embeddings",
}

#: Automata by hand: transitions "state label state" (^ before a label inverts it), start states, final states.
_BENCH = [
    ("0 bulk_supply 1; 1 sourced_from 2; 2 located 3", "0", "3"),
    ("0 bulk_supply 1; 1 sourced_from 2; 2 located 3; 0 located 4; 4 adjacent 5; 5 adjacent 6", "0", "3 6"),
    ("0 adjacent 0", "0", "0"),
    ("0 adjacent 0; 0 within 1", "0", "1"),
    ("0 adjacent 1; 1 adjacent 1", "0", "1"),
    ("0 bulk_supply 1; 1 sourced_from 0", "0", "0"),
    ("0 ordered_by 1; 1 resident_of 2; 2 adjacent 3; 2 within 3", "0", "3"),
    ("0 ordered_by 1; 1 resident_of 2; 2 adjacent 2; 2 within 2", "0", "2"),
    ("0 located 1; 0 resident_of 1; 1 adjacent 2; 1 within 2", "0", "2"),
    ("0 located 1; 0 resident_of 1; 1 adjacent 1; 1 within 1", "0", "1"),
]
AUTOMATA = {f"bench{2 * i + k:02d}_{'sd'[k - 1]}": a for i, a in enumerate(_BENCH) for k in (1, 2)}
AUTOMATA |= {
    "chain7_1": ("0 sourced_from 1; 1 located 2; 2 adjacent 3; 3 adjacent 3; 3 within 4; 4 within 4", "0", "4"),
    "chain7_2": ("0 ordered_by 1; 1 resident_of 2; 2 adjacent 3; 3 adjacent 3; 3 within 4; 4 within 4", "0", "4"),
    "chain7_3": ("0 is_customer 1; 1 placed 2; 2 follows 3; 3 follows 3; 3 has_item 4; 4 has_item 4", "0", "4"),
    "chain7_4": ("0 ^is_customer 1; 1 acted 2; 2 then 3; 3 then 3; 3 event_kind 4; 4 event_kind 4", "0", "4"),
    "chain7_5": ("0 has_item 1; 1 of_part 2; 2 succ_part 3; 3 succ_part 3; 3 made_by 4; 4 made_by 4", "0", "4"),
    "chain7_6": ("0 placed 1; 1 has_item 2; 2 of_part 3; 3 of_part 3; 3 succ_part 4; 4 succ_part 4", "0", "4"),
    "chain7_7": ("0 ordered_by 1; 1 ^ordered_by 2; 2 follows 3; 3 follows 3; 3 has_item 4; 4 has_item 4", "0", "4"),
    "log_01": ("0 placed 1", "0", "1"),
    "log_02": ("0 placed 1; 1 has_item 2", "0", "2"),
    "log_03": ("0 is_customer 1; 1 placed 2; 2 has_item 3; 3 of_part 4", "0", "4"),
    "log_04": ("0 follows 1; 1 follows 1", "0", "1"),
    "log_05": ("0 then 0", "0", "0"),
    "log_06": ("0 ordered_by 1", "0", "0 1"),
    "log_07": ("0 adjacent 0; 0 within 0", "0", "0"),
    "log_08": ("0 located 1; 1 adjacent 1", "0", "1"),
    "log_09": ("0 succ_part 0; 0 made_by 1", "0", "1"),
    "log_10": ("0 ^within 1", "0", "1"),
    "log_11": ("0 ^ordered_by 1; 1 has_item 2", "0", "2"),
    "log_12": ("0 resident_of 1; 1 ^resident_of 2", "0", "2"),
    "log_13": ("0 links 1; 1 ^links 2; 2 links 1", "0", "2"),
    "log_14": ("0 bulk_supply 1; 1 sourced_from 0", "0", "0"),
    "log_15": ("0 adjacent 1; 0 ^adjacent 1; 1 adjacent 1; 1 ^adjacent 1", "0", "1"),
    "log_16": ("0 ^within 0; 0 adjacent 1; 1 adjacent 1; 1 within 2; 2 ^within 0", "0", "0"),
    "log_17": ("0 within 1", "0", "1"),
    "log_18": ("0 within 1; 1 within 2", "0", "2"),
    "log_19": ("0 adjacent 0", "0", "0"),
    "log_20": ("0 within 0", "0", "0"),
    "log_21": ("0 located 1; 0 resident_of 1; 1 within 2", "0", "2"),
    "log_22": ("0 reply 0", "0", "0"),
    "log_23": ("0 near 1; 1 near 1; 1 in_class 2", "0", "2"),
    "log_24": ("0 same_text 1; 1 same_text 1; 1 in_lang 2", "0", "2"),
    "log_25": ("0 event_kind 1", "0", "1"),
    "log_26": ("0 succ_part 1; 1 succ_part 1; 1 made_by 2", "0", "2"),
    "log_27": ("0 quotes 1; 1 ^quotes 2", "0", "2"),
}


def parts(name: str, turned: bool) -> tuple[list[tuple[int, str, int, int]], list[int], list[int]]:
    """Transitions (q, label, inv, q2), starts and finals of an automaton, turned round for a fixed end vertex."""
    rules, starts, finals = AUTOMATA[name]
    moves = [(int(a), x.lstrip("^"), int(x[0] == "^"), int(b)) for a, x, b in (r.split() for r in rules.split(";"))]
    s, f = [int(x) for x in starts.split()], [int(x) for x in finals.split()]
    return ([(b, x, 1 - i, a) for a, x, i, b in moves], f, s) if turned else (moves, s, f)


def edge_cte(labels) -> str:
    return " UNION ALL ".join(f"SELECT DISTINCT '{x}' AS label, src, dst FROM ({EDGES[x]})" for x in sorted(labels))


def _query(moves, starts, finals, seeds: str, select: str, where: str = "") -> str:
    labels = {m[1] for m in moves}
    return f"""
        WITH RECURSIVE edge AS ({edge_cte(labels)}),
          hop AS (SELECT label, 0 AS inv, src, dst FROM edge UNION ALL SELECT label, 1, dst, src FROM edge),
          rule(q, label, inv, q2) AS (VALUES {", ".join(f"({a}, '{x}', {i}, {b})" for a, x, i, b in moves)}),
          begin(q) AS (VALUES {", ".join(f"({q})" for q in starts)}),
          seed(vid) AS ({seeds}),
          seen(seed, q, v) AS (
            SELECT CAST(seed.vid AS BIGINT), begin.q, CAST(seed.vid AS BIGINT) FROM seed, begin
            UNION
            SELECT seen.seed, rule.q2, hop.dst FROM seen JOIN rule ON rule.q = seen.q JOIN hop ON hop.label = rule.label AND hop.inv = rule.inv AND hop.src = seen.v)
        SELECT DISTINCT {select} FROM seen WHERE q IN ({", ".join(map(str, finals))}){where}"""


def one_seed(name: str, turned: bool, vertex: int, select: str = "v", states=None) -> str:
    moves, starts, finals = parts(name, turned)
    return _query(moves, starts, finals if states is None else states, f"SELECT {vertex}", select)


def many_seeds(name: str, turned: bool, kind: int, most: int = 1000, select: str = "seed, v") -> str:
    moves, starts, finals = parts(name, turned)
    low = kind * _ROOM
    seeds = f"""SELECT x FROM (SELECT DISTINCT unnest([src, dst]) AS x FROM edge) WHERE x >= {low} AND x < {low + _ROOM}
                ORDER BY ((x - {low}) % 2147483648) * 2654435761 % 4294967296, x LIMIT {most}"""
    return _query(moves, starts, finals, seeds, select)


def leveled(name: str, turned: bool, vertex: int, levels: int) -> str:
    """level, q, v: the first level of each pair, up to a number of levels."""
    moves, starts, _ = parts(name, turned)
    labels = {m[1] for m in moves}
    return f"""
        WITH RECURSIVE edge AS ({edge_cte(labels)}),
          hop AS (SELECT label, 0 AS inv, src, dst FROM edge UNION ALL SELECT label, 1, dst, src FROM edge),
          rule(q, label, inv, q2) AS (VALUES {", ".join(f"({a}, '{x}', {i}, {b})" for a, x, i, b in moves)}),
          seen(level, q, v) AS (
            SELECT 0, q, CAST({vertex} AS BIGINT) FROM (VALUES {", ".join(f"({q})" for q in starts)}) s(q)
            UNION
            SELECT level + 1, rule.q2, hop.dst FROM seen JOIN rule ON rule.q = seen.q JOIN hop ON hop.label = rule.label AND hop.inv = rule.inv AND hop.src = seen.v WHERE level < {levels})
        SELECT min(level) AS level, q, v FROM seen GROUP BY q, v"""
