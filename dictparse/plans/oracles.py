"""DuckDB SQL that parses by brute force: no trie, no index, every earlier string compared. Independent of the kernels.

Builders take `source`, SQL that returns (id, t), and give CTE lists; a parse `name` ends in a relation `name`(id, x, beg, len, kind,
piece, ref1, sym1, ref2, sym2, power).
"""

from __future__ import annotations

PAIRS = ("pair", "pair_cut", "pair_run")


def _let(name: str, value: str, body: str) -> str:
    return f"list_transform([{value}], lambda {name}: {body})[1]"


def common(a: str, b: str) -> str:
    """Length of the common prefix of two strings."""
    return f"len(list_filter(range(1, least(length({a}), length({b})) + 1), lambda l: left({a}, l) = left({b}, l)))"


def longest_entry(strings: str, rest: str) -> str:
    return f"coalesce(list_max(list_transform(list_filter({strings}, lambda e: starts_with({rest}, e)), lambda e: length(e))), 0)"


def longest_cut(strings: str, rest: str) -> str:
    near = f"list_filter({strings}, lambda e: left(e, 1) = left({rest}, 1))"
    return f"coalesce(list_max(list_transform({near}, lambda e: {common('e', rest)})), 0)"


def longest_power(strings: str, rest: str) -> str:
    """The longest power of a whole string that begins the rest."""
    reach = common(f"repeat(e, CAST(ceil(length({rest}) / length(e)) AS BIGINT))", rest)
    return f"coalesce(list_max(list_transform(list_filter({strings}, lambda e: length(e) > 0 AND starts_with({rest}, e)), lambda e: {reach})), 0)"


def power_base(strings: str, rest: str, reach: str) -> str:
    """The shortest string whose power reaches so far."""
    own = common(f"repeat(e, CAST(ceil(length({rest}) / length(e)) AS BIGINT))", rest)
    return f"list_min(list_transform(list_filter({strings}, lambda e: length(e) > 0 AND starts_with({rest}, e) AND {own} = {reach}), lambda e: length(e)))"


def symbol_run(rest: str) -> str:
    run = common(f"repeat(left({rest}, 1), length({rest}))", rest)
    return f"CASE WHEN {run} >= 2 THEN {run} ELSE 0 END"


def _named(strings: str, word: str) -> str:
    """The number that stands for a string: its own, else that of the first string it begins."""
    return f"coalesce(list_position({strings}, {word}), list_position(list_transform({strings}, lambda e: starts_with(e, {word})), true))"


def _step_sql(scheme: str, run: str) -> str:
    """One factor of every unfinished text of `run`(id, t, n, pos, ds, outs): adds len, kind and token columns."""
    rest = "substr(t, pos)"
    null = "NULL::INTEGER AS {}, NULL::VARCHAR AS {}"
    if scheme == "step":
        return f"""SELECT *, CASE WHEN pos + e1 > n THEN e1 ELSE e1 + 1 END AS len, CASE WHEN pos + e1 > n THEN 'entry' ELSE 'extend' END AS kind,
          CAST(CASE WHEN e1 = 0 THEN 0 ELSE {_named('ds', 'substr(t, pos, e1)')} END AS INTEGER) AS ref1, NULL::VARCHAR AS sym1,
          NULL::INTEGER AS ref2, CASE WHEN pos + e1 > n THEN NULL ELSE substr(t, pos + e1, 1) END AS sym2, NULL::INTEGER AS power
        FROM (SELECT *, {longest_entry('ds', rest)} AS e1 FROM {run} WHERE pos <= n)"""
    if scheme == "seeded":
        return f"""SELECT *, greatest(1, e1) AS len, 'entry' AS kind,
          CAST(CASE WHEN e1 > 1 THEN {_named('ds', 'substr(t, pos, e1)')} END AS INTEGER) AS ref1, CASE WHEN e1 > 1 THEN NULL ELSE substr(t, pos, 1) END AS sym1,
          {null.format('ref2', 'sym2')}, NULL::INTEGER AS power
        FROM (SELECT *, {longest_entry('ds', rest)} AS e1 FROM {run} WHERE pos <= n)"""
    cut = longest_cut("ds", rest) if scheme != "pair" else "0"
    powers = scheme in ("pair_run", "step_run")
    reach, run_length = (longest_power("ds", rest), symbol_run(rest)) if powers else ("0", "0")
    if scheme == "step_run":
        return f"""SELECT *, greatest(a, c1, p1, s1) AS len,
          CASE WHEN a >= greatest(c1, p1, s1) THEN CASE WHEN pos + e1 > n THEN 'entry' ELSE 'extend' END WHEN c1 >= greatest(p1, s1) THEN 'cut' ELSE 'repeat' END AS kind,
          {null.format('ref1', 'sym1')}, {null.format('ref2', 'sym2')}, NULL::INTEGER AS power
        FROM (SELECT *, CASE WHEN pos + e1 > n THEN e1 ELSE e1 + 1 END AS a
        FROM (SELECT *, {longest_entry('ds', rest)} AS e1, {cut} AS c1, {reach} AS p1, {run_length} AS s1 FROM {run} WHERE pos <= n))"""
    second = (longest_entry if scheme == "pair" else longest_cut)("ds", "substr(t, pos + l1)")
    base = f"CASE WHEN p1 > greatest(a, c1, s1) THEN {power_base('ds', rest, 'p1')} END" if powers else "0"
    return f"""SELECT *,
          CASE kind WHEN 'combine' THEN CASE WHEN e1 > 1 THEN {_named('ds', 'substr(t, pos, e1)')} END WHEN 'cut' THEN {_named('ds', 'substr(t, pos, c1)')}
            ELSE CASE WHEN s1 >= p1 THEN NULL ELSE {_named('ds', 'substr(t, pos, b1)')} END END::INTEGER AS ref1,
          CASE kind WHEN 'combine' THEN CASE WHEN e1 > 1 THEN NULL ELSE substr(t, pos, 1) END WHEN 'repeat' THEN CASE WHEN s1 >= p1 THEN substr(t, pos, 1) END END AS sym1,
          CASE WHEN kind <> 'combine' THEN NULL WHEN pos + l1 > n THEN 0 WHEN e2 > 1 THEN {_named('ds', 'substr(t, pos + l1, e2)')} END::INTEGER AS ref2,
          CASE WHEN kind = 'combine' AND pos + l1 <= n AND e2 <= 1 THEN substr(t, pos + l1, 1) END AS sym2,
          CASE kind WHEN 'cut' THEN 1 WHEN 'repeat' THEN CAST(ceil(len / (CASE WHEN s1 >= p1 THEN 1 ELSE b1 END)) AS INTEGER) END AS power
        FROM (SELECT *, greatest(a, c1, p1, s1) AS len, CASE WHEN a >= greatest(c1, p1, s1) THEN 'combine' WHEN c1 >= greatest(p1, s1) THEN 'cut' ELSE 'repeat' END AS kind,
          {base} AS b1
        FROM (SELECT *, l1 + CASE WHEN pos + l1 > n THEN 0 ELSE greatest(1, e2) END AS a
        FROM (SELECT *, {second} AS e2
        FROM (SELECT *, greatest(1, e1) AS l1
        FROM (SELECT *, {longest_entry('ds', rest)} AS e1, {cut} AS c1, {reach} AS p1, {run_length} AS s1 FROM {run} WHERE pos <= n)))))"""


def greedy(scheme: str, source: str, name: str | None = None) -> str:
    """CTEs (for WITH RECURSIVE) that end in the factor relation."""
    name = name or scheme
    added = "list_append(ds, substr(t, pos, len))" if scheme != "seeded" else "CASE WHEN pos + len <= n THEN list_append(ds, substr(t, pos, len + 1)) ELSE ds END"
    return f"""{name}_run(id, t, n, pos, ds, outs) USING KEY (id) AS (
  SELECT id, t, length(t) AS n, 1 AS pos, []::VARCHAR[] AS ds, []::STRUCT(beg BIGINT, len BIGINT, kind VARCHAR, ref1 INTEGER, sym1 VARCHAR, ref2 INTEGER, sym2 VARCHAR, power INTEGER)[] AS outs FROM ({source})
  UNION
  SELECT id, t, n, pos + len, {added}, list_append(outs, {{'beg': pos, 'len': len, 'kind': kind, 'ref1': ref1, 'sym1': sym1, 'ref2': ref2, 'sym2': sym2, 'power': power}}) FROM (
    {_step_sql(scheme, name + '_run')})),
{name} AS MATERIALIZED (
  SELECT id, CAST(x AS INTEGER) AS x, o.beg AS beg, CAST(o.len AS INTEGER) AS len, o.kind AS kind, substr(t, o.beg, o.len) AS piece,
         o.ref1 AS ref1, o.sym1 AS sym1, o.ref2 AS ref2, o.sym2 AS sym2, o.power AS power, n
  FROM (SELECT id, t, n, unnest(outs) AS o, unnest(range(1, len(outs) + 1)) AS x FROM {name}_run))"""


def _greedy_length(scheme: str, strings: str, rest: str) -> str:
    """Length of the greedy factor at the head of `rest`, over a list of strings."""
    if scheme == "seeded":
        return f"greatest(1, {longest_entry(strings, rest)})"
    ahead = f"substr({rest}, a + 1)"
    pair = _let("a", f"greatest(1, {longest_entry(strings, rest)})", f"a + CASE WHEN a >= length({rest}) THEN 0 ELSE greatest(1, {longest_cut(strings, ahead)}) END")
    options = [pair, longest_cut(strings, rest)]
    if scheme == "pair_run":
        options += [longest_power(strings, rest), symbol_run(rest)]
    return f"greatest({', '.join(options)})"


def flex_fixed(scheme: str, source: str, name: str) -> str:
    """Look-ahead over the greedy factors; WITH RECURSIVE CTEs that end in name(id, x, beg, len, piece)."""
    slack = 1 if scheme == "seeded" else 0
    return f"""{greedy(scheme, source, name + '_g')},
{name}_entries AS (SELECT id, list({{'s': {'piece' if not slack else 'whole'}, 'stop': beg + len + {slack}}} ORDER BY x) AS es FROM (
  SELECT g.*, {'substr(s.t, beg, len + 1)' if slack else 'piece'} AS whole FROM {name}_g g JOIN ({source}) s USING (id) WHERE beg + len + {slack} - 1 <= n) GROUP BY id),
{name}_reach AS MATERIALIZED (
  SELECT id, p, {_greedy_length(scheme, 'd', 'r')} AS g FROM (
    SELECT id, p, substr(t, p) AS r, list_transform(list_filter(coalesce(es, []), lambda e: e.stop - {slack} <= p), lambda e: e.s) AS d
    FROM (SELECT id, t, es, unnest(range(1, length(t) + 1)) AS p FROM ({source}) LEFT JOIN {name}_entries USING (id)))),
{name}_best AS MATERIALIZED (
  SELECT a.id, a.p, a.k AS len FROM (SELECT id, p, g, unnest(range(1, g + 1)) AS k FROM {name}_reach) a
  LEFT JOIN {name}_reach b ON a.id = b.id AND b.p = a.p + a.k
  QUALIFY row_number() OVER (PARTITION BY a.id, a.p ORDER BY a.k + coalesce(b.g, 0) DESC, a.k DESC) = 1),
{name}_walk(id, x, p, len) AS (
  SELECT id, 1, p, len FROM {name}_best WHERE p = 1
  UNION ALL
  SELECT w.id, w.x + 1, b.p, b.len FROM {name}_walk w JOIN {name}_best b ON b.id = w.id AND b.p = w.p + w.len),
{name} AS (SELECT w.id, CAST(x AS INTEGER) AS x, CAST(p AS BIGINT) AS beg, CAST(len AS INTEGER) AS len, substr(t, p, len) AS piece FROM {name}_walk w JOIN ({source}) USING (id))"""


def flex_stepwise(scheme: str, lookahead: str, source: str, name: str) -> str:
    """flex_own or flex_longest: the dictionary grows with the parse."""
    slack = 1 if scheme == "seeded" else 0
    at = lambda p: f"list_transform(list_filter(es, lambda e: e.stop - {slack} <= {p}), lambda e: e.s)"
    ahead_es = at("pos + k")
    if lookahead == "flex_own":
        ahead, grown = f"list_append({ahead_es}, substr(t, pos, k))", "list_append(es, {'s': substr(t, pos, k), 'stop': pos + k})"
    else:
        fresh = f"{{'s': substr(t, pos, g + {slack}), 'stop': pos + g + {slack}}}"
        grown = f"CASE WHEN pos + g + {slack} - 1 <= n THEN list_append(es, {fresh}) ELSE es END"
        ahead = ahead_es.replace("(es,", f"({grown},")
    return f"""{name}_run(id, t, n, pos, es, outs) USING KEY (id) AS (
  SELECT id, t, length(t) AS n, 1 AS pos, []::STRUCT(s VARCHAR, stop BIGINT)[] AS es, []::STRUCT(beg BIGINT, len BIGINT, g BIGINT)[] AS outs FROM ({source})
  UNION
  SELECT id, t, n, pos + k, {grown}, list_append(outs, {{'beg': pos, 'len': k, 'g': g}}) FROM (
    SELECT id, t, n, pos, es, outs, g, list_sort(list_transform(range(1, g + 1), lambda k: {{'total': k + CASE WHEN pos + k > n THEN 0 ELSE {_greedy_length(scheme, ahead, 'substr(t, pos + k)')} END, 'k': k}}))[-1].k AS k FROM (
      SELECT *, {_greedy_length(scheme, at('pos'), 'substr(t, pos)')} AS g FROM {name}_run WHERE pos <= n))),
{name} AS (
  SELECT id, CAST(x AS INTEGER) AS x, o.beg AS beg, CAST(o.len AS INTEGER) AS len, substr(t, o.beg, o.len) AS piece, CAST(o.g AS INTEGER) AS entry_len
  FROM (SELECT id, t, unnest(outs) AS o, unnest(range(1, len(outs) + 1)) AS x FROM {name}_run))"""


def parse(full: str, source: str, name: str) -> str:
    """CTEs of 'scheme' or 'scheme+lookahead'."""
    scheme, _, lookahead = full.partition("+")
    if not lookahead:
        return greedy(scheme, source, name)
    return flex_fixed(scheme, source, name) if lookahead == "flex_fixed" else flex_stepwise(scheme, lookahead, source, name)
