"""DuckDB SQL that says the same as the engine, by other means: traces are strings of one letter per event, a tree is
the list of its words, and a word is found by ``LIKE``. Places are found by nested searches in the string."""

from __future__ import annotations

from .lattice import regular_seeds
from .language import words
from .tree import Tree, canonical_word, orders, parse_tree

#: Activities of the views at hand, in order.
STATUS = ("F", "O", "P")
EVENT_TYPES = ("click", "error", "purchase", "signup", "view")
ROLES = ("assistant", "system", "user")
LINE_KINDS = ("AF", "AO", "NF", "NO", "RF", "RO")

EVENTS_OF = {
    "log_user_week": "SELECT user_id::VARCHAR || '|' || strftime(date_trunc('week', ts), '%Y-%m-%d') AS case_id, event_type AS act, row_number() OVER (PARTITION BY user_id, date_trunc('week', ts) ORDER BY ts, event_id) AS pos FROM events",
    "log_user_week_rich": "SELECT user_id::VARCHAR || '|' || strftime(date_trunc('week', ts), '%Y-%m-%d') AS case_id, event_type || '-' || CASE WHEN value < 20 THEN 'lo' WHEN value < 60 THEN 'mid' ELSE 'hi' END AS act, row_number() OVER (PARTITION BY user_id, date_trunc('week', ts) ORDER BY ts, event_id) AS pos FROM events",
    "log_cust_status": "SELECT o_custkey::VARCHAR AS case_id, o_orderstatus AS act, row_number() OVER (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey) AS pos FROM orders",
    "log_order_lines": "SELECT l_orderkey::VARCHAR AS case_id, l_returnflag || l_linestatus AS act, row_number() OVER (PARTITION BY l_orderkey ORDER BY l_shipdate, l_linenumber, l_partkey, l_suppkey, l_returnflag || l_linestatus) AS pos FROM lineitem",
    "log_order_parts": "SELECT l_orderkey::VARCHAR AS case_id, p_type AS act, row_number() OVER (PARTITION BY l_orderkey ORDER BY l_shipdate, l_linenumber, l_partkey, l_suppkey, p_type) AS pos FROM lineitem JOIN part ON l_partkey = p_partkey",
    "log_conv": "SELECT conv_id::VARCHAR AS case_id, role AS act, row_number() OVER (PARTITION BY conv_id ORDER BY turn, role) AS pos FROM conversations",
    "log_user": "SELECT user_id::VARCHAR AS case_id, event_type AS act, row_number() OVER (PARTITION BY user_id ORDER BY ts, event_id) AS pos FROM events",
    "log_user_rich": "SELECT user_id::VARCHAR AS case_id, event_type || '-' || CASE WHEN value < 20 THEN 'lo' WHEN value < 60 THEN 'mid' ELSE 'hi' END AS act, row_number() OVER (PARTITION BY user_id ORDER BY ts, event_id) AS pos FROM events",
    "log_user_3day": "SELECT user_id::VARCHAR || '|' || (date_diff('day', DATE '2024-01-01', ts::DATE) // 3)::VARCHAR AS case_id, event_type AS act, row_number() OVER (PARTITION BY user_id, date_diff('day', DATE '2024-01-01', ts::DATE) // 3 ORDER BY ts, event_id) AS pos FROM events",
    "log_user_day": "SELECT user_id::VARCHAR || '|' || strftime(ts, '%Y-%m-%d') AS case_id, event_type AS act, row_number() OVER (PARTITION BY user_id, strftime(ts, '%Y-%m-%d') ORDER BY ts, event_id) AS pos FROM events",
    "log_cust_priority": "SELECT o_custkey::VARCHAR AS case_id, o_orderpriority AS act, row_number() OVER (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey) AS pos FROM orders",
    "log_cust_status_prio": "SELECT o_custkey::VARCHAR AS case_id, o_orderstatus || '-' || substr(o_orderpriority, 1, 1) AS act, row_number() OVER (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey) AS pos FROM orders",
    "log_conv_rich": "SELECT conv_id::VARCHAR AS case_id, role || '-' || least(length(text) // 150, 8)::VARCHAR AS act, row_number() OVER (PARTITION BY conv_id ORDER BY turn, role || '-' || least(length(text) // 150, 8)::VARCHAR) AS pos FROM conversations",
}
EVENTS_OF |= {f"log_sample{k}0": EVENTS_OF["log_cust_status_prio"] + f" WHERE o_custkey % 10 < {k}" for k in (3, 4)}
ALPHABET = {"log_user_week": EVENT_TYPES, "log_user_rich": tuple(f"{e}-{b}" for e in EVENT_TYPES for b in ("hi", "lo", "mid")), "log_cust_status": STATUS, "log_order_lines": LINE_KINDS, "log_conv": ROLES}


def letter(view: str, a: str) -> str:
    return chr(97 + ALPHABET[view].index(a))


def traces_sql(view: str) -> str:
    """Readable traces: ``case_id, trace, n``."""
    return f"SELECT case_id, string_agg(act, ' ' ORDER BY pos) AS trace, count(*)::INTEGER AS n FROM ({EVENTS_OF[view]}) GROUP BY case_id"


def coded_cte(view: str, events: str | None = None) -> str:
    """CTE ``log(case_id, s)`` with one letter per event."""
    codes = ", ".join(f"('{a}', '{letter(view, a)}')" for a in ALPHABET[view])
    return f"ev AS ({events or EVENTS_OF[view]}), log AS (SELECT case_id, string_agg(code, '' ORDER BY pos) AS s FROM ev JOIN (VALUES {codes}) AS d(act, code) USING (act) GROUP BY case_id)"


def _likes(view: str, t: Tree, compact: bool) -> list[str]:
    found = words(t, 2, compact)
    short = {w for w in found if not any(w != v and len(v) < len(w) and _within(v, w) for v in found)} if len(found) < 50 else found
    return ["%" + "%".join(letter(view, a) for a in w) + "%" for w in sorted(short)]


def _within(v: tuple, w: tuple) -> bool:
    it = iter(w)
    return all(a in it for a in v)


def patterns_cte(view: str, trees: list[str], compact: bool = True) -> str:
    """CTE ``counts(tree, n_hits)`` of trees by ``LIKE`` over their words; trees without a hit count zero."""
    rows = ", ".join(f"('{t}', '{p}')" for t in trees for p in _likes(view, parse_tree(t), compact))
    return f"pats(tree, pat) AS (VALUES {rows}), hits AS (SELECT DISTINCT tree, case_id FROM pats JOIN log ON s LIKE pat), counts AS (SELECT p.tree, count(h.case_id) AS n_hits FROM (SELECT DISTINCT tree FROM pats) p LEFT JOIN hits h USING (tree) GROUP BY p.tree)"


def support_sql(view: str, trees: list[str], compact: bool = True, with_support: bool = True) -> str:
    ratio = ", (SELECT count(*) FROM log) AS n_cases, round(n_hits / (SELECT count(*) FROM log), 6) AS support" if with_support else ""
    return f"WITH {coded_cte(view)}, {patterns_cte(view, trees, compact)} SELECT tree, n_hits{ratio} FROM counts"


def generations(trees: list[str]) -> list[tuple[str, int, str, str, str]]:
    """``(tree, leaves, operator, seed1, seed2)`` for every order in which a combination makes the tree."""
    out = set()
    for w in trees:
        for v in orders(parse_tree(w)):
            s1, s2, _, _ = regular_seeds(v)
            point = max((p for p, x in v.leaves() if len(p) == v.depth))[:-1]
            out.add((w, v.n_leaves, v.at(point).op, canonical_word(s1), canonical_word(s2)))
    return sorted(out)


def mined_sql(view: str, trees: list[str], tau: float, columns: str = "tree, n_hits", where: str = "TRUE", events: str | None = None, kept: bool = False) -> str:
    """The mined set among an exhaustive list of trees, level by level: constraining operators ask for frequent seeds, a
    choice for two infrequent ones that occur. ``kept`` drops seeds of frequent trees and trees whose concurrency is
    one-sided."""
    gens = ", ".join(f"('{a}', {n}, '{op}', '{s1}', '{s2}')" for a, n, op, s1, s2 in generations(trees))
    most = max(parse_tree(t).n_leaves for t in trees)
    probes = sorted({str(v) for t in trees for v in _and_probes(parse_tree(t))} - set(trees)) if kept else []
    parts = [coded_cte(view, events), patterns_cte(view, trees + probes), f"gens(tree, k, op, s1, s2) AS (VALUES {gens})",
             f"need AS (SELECT ceil({tau} * count(*) - 1e-9) AS n FROM log)",
             "f2 AS (SELECT DISTINCT tree, n_hits FROM counts JOIN gens USING (tree), need WHERE k = 2 AND n_hits >= n)",
             "i2 AS (SELECT DISTINCT tree, n_hits FROM counts JOIN gens USING (tree), need WHERE k = 2 AND n_hits < n AND n_hits > 0)"]
    for k in range(3, most + 1):
        b = k - 1
        parts.append(
            f"c{k} AS (SELECT DISTINCT g.tree, c.n_hits FROM gens g JOIN counts c ON c.tree = g.tree WHERE g.k = {k} AND ("
            f"(op <> 'xor' AND s1 IN (SELECT tree FROM f{b}) AND s2 IN (SELECT tree FROM f{b})) OR "
            f"(op = 'xor' AND s1 IN (SELECT tree FROM i{b}) AND s2 IN (SELECT tree FROM i{b}) AND "
            f"(SELECT n_hits FROM i{b} WHERE tree = s1) + (SELECT n_hits FROM i{b} WHERE tree = s2) >= (SELECT n FROM need))))"
        )
        parts.append(f"f{k} AS (SELECT c{k}.* FROM c{k}, need WHERE n_hits >= n), i{k} AS (SELECT c{k}.* FROM c{k}, need WHERE n_hits < n AND n_hits > 0)")
    parts.append("freq AS (" + " UNION ALL ".join(f"SELECT * FROM f{k}" for k in range(2, most + 1)) + ")")
    if kept:
        pairs = ", ".join(f"('{t}', '{x}')" for t in trees for x in map(str, _and_probes(parse_tree(t)))) or "('', '')"
        parts.append("drop_seed AS (SELECT s1 AS tree FROM gens JOIN freq USING (tree) UNION SELECT s2 FROM gens JOIN freq USING (tree))")
        parts.append(f"probe(tree, v) AS (VALUES {pairs}), one_sided AS (SELECT DISTINCT p.tree FROM probe p JOIN counts c ON c.tree = p.v WHERE c.n_hits < 1)")
        where += " AND tree NOT IN (SELECT tree FROM drop_seed) AND tree NOT IN (SELECT tree FROM one_sided)"
    return f"WITH {', '.join(parts)} SELECT {columns} FROM freq WHERE {where}"


def _and_probes(t: Tree) -> list[Tree]:
    out = []
    for path, x in t.nodes():
        if x.op == "and":
            out += [t.replace(path, Tree("seq", None, a, b)) for a, b in ((x.left, x.right), (x.right, x.left))]
    return out


class Places:
    """Chained subqueries that add the places ``p0, p1, …`` of a tree's match to a table with column ``s``."""

    def __init__(self, view: str, tree: str, prefix: str = "p"):
        self.view, self.steps, self.prefix, self.names = view, [], prefix, []
        self.end = self._add(parse_tree(tree), "0")

    def _add(self, t: Tree, start: str) -> str:
        if t.is_leaf:
            name = f"{self.prefix}{len(self.names)}"
            found = f"strpos(substr(s, ({start}) + 1), '{letter(self.view, t.label)}')"
            self.steps.append(f"CASE WHEN ({start}) IS NULL OR {found} = 0 THEN NULL ELSE ({start}) + {found} END AS {name}")
            self.names.append((name, t.label))
            return name
        if t.op == "seq":
            return self._add(t.right, self._add(t.left, start))
        if t.op == "loop":
            return self._add(t.left, self._add(t.right, self._add(t.left, start)))
        x, y = self._add(t.left, start), self._add(t.right, start)
        both = "IS NULL OR" if t.op == "and" else "IS NULL AND"
        pick = "greatest" if t.op == "and" else "least"
        return f"CASE WHEN ({x}) {both} ({y}) IS NULL THEN NULL ELSE {pick}({x}, {y}) END"

    def over(self, table: str) -> str:
        for step in self.steps:
            table = f"(SELECT *, {step} FROM {table})"
        return table

    @property
    def all(self) -> list[str]:
        return [n for n, _ in self.names]


def bounds_sql(view: str, trees: list[str]) -> str:
    """CTE body ``case_id, tree, lo, hi`` of matches."""
    parts = []
    for t in trees:
        p = Places(view, t)
        parts.append(f"SELECT case_id, '{t}' AS tree, least({', '.join(p.all)})::INTEGER AS lo, greatest({', '.join(p.all)})::INTEGER AS hi FROM {p.over('log')} WHERE ({p.end}) IS NOT NULL")
    return " UNION ALL ".join(parts)


def profile_sql(view: str) -> str:
    return f"SELECT count(*) AS n_cases, sum(n)::BIGINT AS n_events, max(n) AS longest, count(DISTINCT trace) AS n_variants FROM ({traces_sql(view)})"


#: A tree over two nodes is one number, as is a tree with a trace.
NODES, TRACES = 100_000, 10_000_000
TREE = "({op}::BIGINT * 100000 + {x}) * 100000 + {y}"
PARTS = "t // 10000000000 AS op0, t // 100000 % 100000 AS x, t % 100000 AS y"


def _hits(trees: str) -> str:
    """``h``, a tree with a trace that has it, for trees ``t`` over nodes whose words and hits are known."""
    own = f"(SELECT t, {PARTS} FROM {trees}) t"
    words = "JOIN words a ON a.id = x JOIN words b ON b.id = y"
    return (
        f"SELECT t * {TRACES} + h.k AS h FROM {own} JOIN hb h ON h.id = x JOIN hb g ON g.id = y AND g.k = h.k WHERE op0 = 1 UNION ALL "
        f"SELECT DISTINCT t * {TRACES} + k FROM {own} {words} JOIN lg ON s LIKE '%' || a.pat || '%' || b.pat || '%' WHERE op0 = 0 UNION ALL "
        f"SELECT DISTINCT t * {TRACES} + k FROM {own} {words} JOIN words c ON c.id = x JOIN lg ON s LIKE '%' || a.pat || '%' || b.pat || '%' || c.pat || '%' WHERE op0 = 2"
    )


def _next(c: str, start: str) -> str:
    found = f"strpos(substr(s, ({start}) + 1), {c})"
    return f"CASE WHEN ({start}) IS NULL OR {found} = 0 THEN NULL ELSE ({start}) + {found} END"


def _match_steps(node: str, start: str, tag: str) -> list[str]:
    """Select lists that add the places and the end of a node ``op, ca, cb`` to a table with the trace ``s``."""
    op, a, b = f"{node}op", f"{node}a", f"{node}b"
    first, end = f"{tag}1", f"{tag}e"
    other = f"CASE WHEN {op} IS NULL THEN NULL WHEN {op} IN (0, 2) THEN {_next(b, first)} ELSE {_next(b, start)} END"
    third = f"CASE WHEN {op} = 2 THEN {_next(a, f'{tag}2')} END"
    return [
        f"{_next(a, start)} AS {first}",
        f"{other} AS {tag}2",
        f"{third} AS {tag}3",
        f"CASE WHEN {op} IS NULL THEN {tag}1 WHEN {op} = 0 THEN {tag}2 WHEN {op} = 1 THEN CASE WHEN {tag}1 IS NOT NULL AND {tag}2 IS NOT NULL THEN greatest({tag}1, {tag}2) END WHEN {op} = 2 THEN {tag}3 ELSE least({tag}1, {tag}2) END AS {end}",
    ]


def _precision(table: str) -> str:
    """CTE body ``t, precision``: distinct words of the leftmost matches over the words of two rounds of loops."""
    rows = f"SELECT f.t, f.op0, a.op AS xop, a.ca AS xa, a.cb AS xb, b.op AS yop, b.ca AS ya, b.cb AS yb, s FROM {table} f JOIN nd a ON a.id = f.x JOIN nd b ON b.id = f.y, lg"
    for step in (*_match_steps("x", "0", "p"), *_match_steps("y", "CASE WHEN op0 = 1 THEN 0 ELSE pe END", "q"), *_match_steps("x", "CASE WHEN op0 = 2 THEN qe END", "r")):
        rows = f"SELECT *, {step} FROM ({rows})"
    # a choice that lies later is not taken
    places = [(f"{t}{k}", f"{node}{'b' if k == 2 else 'a'}", f"({node}op IS DISTINCT FROM 3 OR {t}{k} = {t}e)") for t, node in (("p", "x"), ("q", "y"), ("r", "x")) for k in (1, 2, 3)]
    pairs = ", ".join(f"CASE WHEN {place} IS NOT NULL AND {taken} THEN lpad({place}::VARCHAR, 9, '0') || {c} END" for place, c, taken in places)
    word = f"array_to_string(list_transform(list_sort(list_filter([{pairs}], lambda v: v IS NOT NULL)), lambda v: substr(v, 10)), '')"
    end = "CASE op0 WHEN 0 THEN qe WHEN 1 THEN CASE WHEN pe IS NOT NULL THEN qe END ELSE re END"
    n = lambda node: f"CASE WHEN any_value({node}op) IN (1, 3) THEN 2 ELSE 1 END"
    size = lambda node: f"CASE WHEN any_value({node}op) IN (0, 1) THEN 2 WHEN any_value({node}op) = 2 THEN 3 ELSE 1 END"
    merges = f"factorial(({size('x')} + {size('y')})::INTEGER) / (factorial(({size('x')})::INTEGER) * factorial(({size('y')})::INTEGER))"
    total = f"({n('x')}) * ({n('y')}) * CASE any_value(op0) WHEN 1 THEN {merges} WHEN 2 THEN ({n('x')}) ELSE 1 END"
    return f"SELECT t, count(DISTINCT word) / ({total}) AS precision FROM (SELECT *, {word} AS word FROM ({rows}) WHERE ({end}) IS NOT NULL) GROUP BY t"


def lattice_sql(view: str, tau: float, choices: bool = True, reported: bool = False, columns: str = "tree, n AS n_hits", where: str = "TRUE", precise: bool = False) -> str:
    """Mining to depth 2 wholly in SQL: trees are made level by level out of the counts, over the distinct traces.

    A tree is an operator (0 seq, 1 and, 2 loop, 3 xor) over two nodes, each an activity or an operator over two
    activities; nodes are numbered in the order of their texts, so that children of ``and`` are ordered by number.
    ``reported`` leaves out regular seeds of frequent trees and trees of which some concurrency is seen in one order only.
    ``precise`` adds the column ``precision``. That a choice has not just one frequent branch is not asked, which matters
    only where both children of a tree are choices.
    """
    ops = "(VALUES (0, 'seq'), (1, 'and'), (2, 'loop')" + (", (3, 'xor')" if choices else "") + ") AS o(op, word)"
    # two seeds that differ in one leaf: frequent ones meet under a constraining operator, infrequent ones under a choice
    allowed = "(q.op <> 3 AND u.n >= need.n AND v.n >= need.n OR q.op = 3 AND u.n BETWEEN 1 AND need.n - 1 AND v.n BETWEEN 1 AND need.n - 1 AND u.n + v.n >= need.n)"
    tree = lambda x, y, op="u.op0": f"CASE WHEN {op} = 1 THEN {TREE.format(op=op, x=f'least({x}, {y})', y=f'greatest({x}, {y})')} ELSE {TREE.format(op=op, x=x, y=y)} END"
    counted = lambda g: f"SELECT t, {PARTS}, coalesce(f.n, 0) AS n FROM (SELECT DISTINCT t FROM {g}) LEFT JOIN (SELECT h // {TRACES} AS t, sum(w)::BIGINT AS n FROM ({_hits(f'(SELECT DISTINCT t FROM {g})')}) JOIN lg ON k = h % {TRACES} GROUP BY h // {TRACES}) f USING (t)"
    ctes = [
        f"ev AS ({EVENTS_OF[view]})",
        "codes AS MATERIALIZED (SELECT act, chr(96 + row_number() OVER (ORDER BY act)::INTEGER) AS c FROM (SELECT DISTINCT act FROM ev))",
        "lg AS MATERIALIZED (SELECT row_number() OVER (ORDER BY s) AS k, s, count(*) AS w FROM (SELECT string_agg(c, '' ORDER BY pos) AS s FROM ev JOIN codes USING (act) GROUP BY case_id) GROUP BY s)",
        f"need AS MATERIALIZED (SELECT greatest(1, ceil({tau} * sum(w) - 1e-9))::BIGINT AS n FROM lg)",
        f"texts AS (SELECT NULL AS op, act AS name, act AS a, NULL AS b, c AS ca, NULL AS cb FROM codes UNION ALL SELECT op, word || '(' || x.act || ',' || y.act || ')', x.act, y.act, x.c, y.c FROM {ops}, codes x, codes y WHERE x.act <> y.act AND (op IN (0, 2) OR x.act < y.act))",
        "nd AS MATERIALIZED (SELECT row_number() OVER (ORDER BY name) AS id, * FROM texts)",
        "pair AS MATERIALIZED (SELECT p.id, p.op, a.id AS a, b.id AS b FROM nd p JOIN nd a ON a.name = p.a AND a.op IS NULL JOIN nd b ON b.name = p.b AND b.op IS NULL)",
        "words AS MATERIALIZED (SELECT id, ca AS pat FROM nd WHERE op IS NULL OR op = 3 UNION ALL SELECT id, cb FROM nd WHERE op = 3 UNION ALL SELECT id, ca || '%' || cb FROM nd WHERE op IN (0, 1) "
        "UNION ALL SELECT id, cb || '%' || ca FROM nd WHERE op = 1 UNION ALL SELECT id, ca || '%' || cb || '%' || ca FROM nd WHERE op = 2)",
        f"hb AS MATERIALIZED (SELECT h // {TRACES} AS id, h % {TRACES} AS k FROM (SELECT DISTINCT id * {TRACES} + k AS h FROM words JOIN lg ON s LIKE '%' || pat || '%'))",
        f"g2 AS MATERIALIZED (SELECT {tree('a', 'b', 'op')} AS t FROM pair WHERE op <> 3)",
        f"n2 AS MATERIALIZED ({counted('g2')})",
        "r2 AS MATERIALIZED (SELECT op0, x, y, n, t FROM n2 UNION ALL SELECT op0, y, x, n, t FROM n2 WHERE op0 = 1)",
        f"g3 AS MATERIALIZED (SELECT {tree('u.x', 'q.id')} AS t, u.t AS s1, v.t AS s2 FROM r2 u JOIN r2 v ON v.op0 = u.op0 AND v.x = u.x AND v.y <> u.y JOIN pair q ON q.a = u.y AND q.b = v.y, need WHERE {allowed} UNION ALL "
        f"SELECT {tree('q.id', 'u.y')}, u.t, v.t FROM r2 u JOIN r2 v ON v.op0 = u.op0 AND v.y = u.y AND v.x <> u.x JOIN pair q ON q.a = u.x AND q.b = v.x, need WHERE {allowed})",
        f"n3 AS MATERIALIZED ({counted('g3')})",
        "r3 AS MATERIALIZED (SELECT op0, n, x AS p, y AS c, t FROM n3 WHERE x IN (SELECT id FROM pair) UNION ALL SELECT op0, n, y, x, t FROM n3 WHERE op0 = 1 AND y IN (SELECT id FROM pair))",
        f"g4 AS MATERIALIZED (SELECT {tree('u.p', 'q.id')} AS t, u.t AS s1, v.t AS s2 FROM r3 u JOIN r3 v ON v.op0 = u.op0 AND v.p = u.p AND v.c <> u.c JOIN pair q ON q.a = u.c AND q.b = v.c, need WHERE {allowed})",
        f"n4 AS MATERIALIZED ({counted('g4')})",
        "freq AS MATERIALIZED (SELECT f.* FROM (SELECT * FROM n2 UNION ALL SELECT * FROM n3 UNION ALL SELECT * FROM n4) f, need WHERE f.n >= need.n)",
    ]
    if reported:
        key = lambda x, y, op="f.op0": TREE.format(op=op, x=x, y=y)
        swap = "SELECT f.t AS own, {v} AS t FROM freq f JOIN pair p ON p.id = f.{side} AND p.op = 1 JOIN pair v ON v.op = 0 AND (v.a = p.a AND v.b = p.b OR v.a = p.b AND v.b = p.a)"
        whole = "SELECT t, {0} FROM freq f WHERE op0 = 1"

        def seeds(table: str) -> str:
            """Both seeds of all orders of the trees; a node of two activities on the left is collapsed if it may be the last."""
            right = [f"SELECT {tree('f.x', f'q.{side}', 'f.op0')} AS t FROM {table} f JOIN pair q ON q.id = f.y" for side in "ab"]
            left = [f"SELECT {tree(f'q.{side}', 'f.y', 'f.op0')} FROM {table} f JOIN pair q ON q.id = f.x WHERE f.op0 = 1 OR f.y NOT IN (SELECT id FROM pair)" for side in "ab"]
            return " UNION ALL ".join(right + left)

        ctes += [
            f"low3 AS MATERIALIZED ({seeds('freq')})",
            f"low2 AS MATERIALIZED ({seeds(f'(SELECT {PARTS} FROM low3)')})",
            "low AS MATERIALIZED (SELECT t AS seed FROM low3 UNION ALL SELECT t FROM low2)",
            f"var AS MATERIALIZED ({swap.format(v=key('v.id', 'f.y'), side='x')} UNION ALL {swap.format(v=key('f.x', 'v.id'), side='y')} UNION ALL {whole.format(key('x', 'y', '0'))} UNION ALL {whole.format(key('y', 'x', '0'))})",
            f"seen AS MATERIALIZED (SELECT DISTINCT h // {TRACES} AS t FROM ({_hits('(SELECT DISTINCT t FROM var)')}))",
            "one_sided AS MATERIALIZED (SELECT own FROM var WHERE t NOT IN (SELECT t FROM seen))",
            "kept AS MATERIALIZED (SELECT t, op0, x, y, n FROM freq WHERE t NOT IN (SELECT seed FROM low) AND t NOT IN (SELECT own FROM one_sided))",
        ]
    table = "kept" if reported else "freq"
    if precise:
        ctes += [f"prec AS MATERIALIZED ({_precision(table)})", f"rated AS (SELECT op0, x, y, n, precision FROM {table} JOIN prec USING (t))"]
        table = "rated"
    ctes.append(f"named AS (SELECT CASE op0 WHEN 0 THEN 'seq' WHEN 1 THEN 'and' ELSE 'loop' END || '(' || names[x] || ',' || names[y] || ')' AS tree, n, n_cases{', precision' if precise else ''} FROM {table}, (SELECT list(name ORDER BY id) AS names FROM nd), (SELECT sum(w) AS n_cases FROM lg))")
    return f"WITH {', '.join(ctes)} SELECT {columns} FROM named WHERE {where}"
