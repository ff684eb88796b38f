"""Bundles of op1: sets that keep a token in common, found on the rows of kept tokens alone."""

import random

from turnwise.llm import jaccard_join


def test_bundles_are_the_components_and_no_join_makes_more_rows_than_there_are(spark, monkeypatch):
    rng = random.Random(3)
    kept = [(s, s // 20 * 100 + rng.randrange(40)) for s in range(600) for _ in range(rng.randrange(1, 9))]
    kept += [(k, 100_000 + k // 2) for k in range(1000, 1300)] + [(k + 1, 200_000 + k // 2) for k in range(1000, 1300)]  # pairs, and a chain of 300
    kept += [(9000 + k, 300_000 + k) for k in range(50)]  # tokens that nobody shares
    root = {s: s for s, _ in kept}

    def find(s):
        while root[s] != s:
            s = root[s]
        return s

    holders = {}
    for s, t in kept:
        a, b = sorted((find(s), find(holders.setdefault(t, s))))
        root[b] = a
    sizes = {}
    for s in root:
        sizes.setdefault(find(s), []).append(s)
    want = {s: r for r, members in sizes.items() if len(members) > 1 for s in members}
    rows, plain = [], jaccard_join.cut

    def counted(df):
        out = plain(df)
        rows.append(out.count())
        return out

    monkeypatch.setattr(jaccard_join, "cut", counted)
    got = jaccard_join.bundled(spark.createDataFrame(kept, "name long, token long")).collect()
    assert len(got) == len(want) and {r["name"]: r["bundle"] for r in got} == want
    assert max(rows) <= len(kept)
    assert jaccard_join.bundled(spark.createDataFrame([(1, 5), (2, 6)], "name long, token long")).collect() == []
