"""Parser and commitments on hand-written statements."""

import pytest

from turnwise.sqltext import SqlError, commitments, parse

KINDS = [
    ("select a from t", {"PROJECT": 1}),
    ("select a, b c from t where x = 1 and y = 2", {"PROJECT": 2, "FILTER": 2}),
    ("select a from t where x = 1 or y = 2", {"PROJECT": 1, "FILTER": 1}),
    ("select a from t where (x = 1 or y = 2) and z like 'q%'", {"PROJECT": 1, "FILTER": 2}),
    ("select a from t join u on t.i = u.i and u.k = 3", {"PROJECT": 1, "FILTER": 1}),
    ("select a from t left join u using (i) where u.v is null", {"PROJECT": 1, "FILTER": 1}),
    ("select a, count(*) from t group by a having count(*) > 5", {"PROJECT": 2, "GROUP": 1, "HAVING": 1}),
    ("select a, sum(b) from t group by 1 order by 2 desc limit 10 offset 5", {"PROJECT": 2, "GROUP": 1, "ORDER": 1, "LIMIT": 1, "OFFSET": 1}),
    ("select distinct a from t order by a asc nulls last", {"PROJECT": 1, "ORDER": 1}),
    ("select a from t where b in (1, 2, 3) and c not in ('x') and d between 1 and 5", {"PROJECT": 1, "FILTER": 3}),
    ("select a from t where exists (select 1 from u where u.i = t.i)", {"PROJECT": 2, "FILTER": 2}),
    ("with z as (select a from t where b = 1) select a from z where a > 2", {"PROJECT": 2, "FILTER": 2}),
    ("select a from t union all select b from u where c = 1", {"PROJECT": 2, "FILTER": 1}),
    ("select case when a > 1 then 'x' else 'y' end from t", {"PROJECT": 1}),
    ("select row_number() over (partition by a order by b desc) from t", {"PROJECT": 1}),
    ('select "A", `b` from t -- note\n where /* inner */ c = 1', {"PROJECT": 2, "FILTER": 1}),
    ("select a from (select b a from t where c = 1) x where a <> 3", {"PROJECT": 2, "FILTER": 2}),
    ("select a, b from t group by rollup(a, b)", {"PROJECT": 2, "GROUP": 2, "GROUP_MODE": 1}),
    ("select cast(a as decimal(10, 2)), b::int from t where d >= date '1996-01-01'", {"PROJECT": 2, "FILTER": 1}),
    ("select a from t where b > all (select c from u)", {"PROJECT": 2, "FILTER": 1}),
    ("select [a b] from (t join u on t.x = u.y) where c glob 'q*' and d like 'x!%' escape '!' and e = 'v' collate nocase", {"PROJECT": 1, "FILTER": 3}),
    ("with z(p, q) as (select a, b from t) select p from z where q = 1", {"PROJECT": 3, "FILTER": 1}),
    ("select extract(year from d), count(distinct x) filter (where y = 1) from t", {"PROJECT": 2}),
]


@pytest.mark.parametrize("sql,want", KINDS)
def test_counts_of_kinds(sql, want):
    found = {}
    for kind, *_ in commitments(sql):
        found[kind] = found.get(kind, 0) + 1
    assert found == want


@pytest.mark.parametrize(
    "a,b",
    [
        ("select a from t where 1 < a", "SELECT t.a FROM t WHERE T.a > 1.00"),
        ("select x.a from t x where x.b = 'q'", "select a from t where 'q' = b"),
        ("select a from t where b in (2, 1)", "select a from t where b in (1, 2.0)"),
        ("select a from t where b = 1 and c = 2", "select a from t where c = 2 and b = 1"),
        ("select a, sum(b) s from t group by a order by s", "select a, sum(b) from t group by 1 order by 2"),
        ("select a from t where x = 1 or y = 2", "select a from t where y = 2 or x = 1"),
        ("select a as q from t", "select a from t"),
    ],
)
def test_equal_intent_is_equal(a, b):
    assert commitments(a) == commitments(b)


def test_levels_and_strict_mode():
    a, b = "select a from t where b = 1", "select a from t where 1 = b"
    assert commitments(a, level="raw") != commitments(b, level="raw")
    assert ("SHAPE", "", "DISTINCT", ()) in commitments("select distinct a from t", strict=True)
    assert not any(k == "SHAPE" for k, *_ in commitments("select distinct a from t"))
    assert {t for k, _, t, _ in commitments("select * from t", schema={"t": ["a", "b"]}) if k == "PROJECT"} == {"t.a", "t.b"}


@pytest.mark.parametrize("bad", ["", "select", "delete from t", "select a from t where", "select 'x", "select a from t group", "drop table t", "select a from t; select b from t"])
def test_rejects(bad):
    with pytest.raises(SqlError):
        parse(bad)


def test_agrees_with_another_parser_on_filters():
    import json

    import duckdb

    con = duckdb.connect()
    for sql, want in KINDS:
        if "filter" in sql or "::" in sql or "`" in sql or "[" in sql:
            continue
        tree = json.loads(con.execute("select json_serialize_sql(?)", [sql]).fetchone()[0] if hasattr(con, "fetchone") else con.execute("select json_serialize_sql(?)", [sql]).fetchall()[0][0])
        assert tree["error"] is False, sql
        node = tree["statements"][0]["node"]
        if node["type"] == "SELECT_NODE" and "with" not in sql and "exists" not in sql and "(select" not in sql:
            where = node["where_clause"]
            n = 0 if where is None else len(where["children"]) if where.get("type") == "CONJUNCTION_AND" else 1
            on = sql.count(" = 3")  # the one literal comparison inside ON
            assert want.get("FILTER", 0) == n + on, sql
            assert want.get("PROJECT") == len(node["select_list"]), sql


NESTED = "select a from t where x in (select y from u where z = {z}{more}) and b = {b}"


@pytest.mark.parametrize(
    "after,lost,gained",
    [
        (NESTED.format(z=2, more=" and w > 5", b=1), 1, 1),  # one literal inside
        (NESTED.format(z=1, more="", b=1), 1, 0),  # one predicate inside
        (NESTED.format(z=1, more=" and w > 5 and v in (1, 2)", b=1), 0, 1),  # one more inside
        (NESTED.format(z=1, more=" and w > 5", b=2), 1, 1),  # one literal outside
        ("select a from t where b = 1", 4, 0),  # the whole nested predicate: itself, its two conditions and its output
    ],
)
def test_nested_changes_count_once(after, lost, gained):
    pre, post = set(commitments(NESTED.format(z=1, more=" and w > 5", b=1))), set(commitments(after))
    assert (len(pre - post), len(post - pre)) == (lost, gained)


def test_nested_scopes_are_apart():
    """Two nested queries, one in the other, a union arm and a derived table each have a scope of their own."""
    got = commitments("select a, (select max(m) from q) from t where x in (select y from u where z = (select min(k) from v)) union select c from (select c from w where d = 1) e")
    assert {s for _, s, _, _ in got} == {"arm:0", "arm:0/sub:1", "arm:0/sub:2", "arm:0/sub:2/sub:1", "arm:1", "arm:1/from:1"}
