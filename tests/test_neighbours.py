"""Pairs of near vectors, triangles and what they are used for, against plain Python."""

import random
from itertools import combinations

from bspflow.algos import structure
from bspflow.graphs import knn_pairs


def test_tiles_find_the_pairs_that_all_comparisons_find(spark, tmp_path):
    r = random.Random(3)
    rows = [(n, n % 2, [r.uniform(-1, 1) for _ in range(4)]) for n in range(40)] + [(50, 0, None), (51, 0, [0.0] * 4), (52, 0, [1.0, None, 0.0, 0.0]), (53, 1, [float("nan")] * 4), (54, 0, [1.0])]
    spark.createDataFrame(rows, "vec_id long, label int, embedding array<double>").write.parquet(f"{tmp_path}/embeddings.parquet")
    cos = lambda x, y: sum(a * b for a, b in zip(x, y)) / (sum(a * a for a in x) * sum(b * b for b in y)) ** 0.5
    want = {(a[0], b[0]): round(cos(a[2], b[2]) * 1e6) for a, b in combinations(rows[:40], 2) if a[1] == b[1] and cos(a[2], b[2]) >= 0.3}
    assert {(x.src, x.dst): x.weight for x in knn_pairs(spark, str(tmp_path), tile=6).collect()} == want


def test_triangles_of_many_colours(spark):
    r = random.Random(5)
    pairs = {(a, b) for a, b in combinations(range(40), 2) if r.random() < 0.3}
    want = {t for t in combinations(range(40), 3) if all(p in pairs for p in combinations(t, 2))}
    got = structure.triangles(spark.createDataFrame(sorted(pairs), "src long, dst long"), edges_a_group=10).collect()
    assert len(got) == len(want) and {tuple(sorted(x)) for x in got} == want


def _recommended(pairs, k):
    near = {}
    for a, b in pairs:
        near.setdefault(a, set()).add(b)
        near.setdefault(b, set()).add(a)
    out = set()
    for v in near:
        found = sorted((-len(near[v] & near[c]), c) for c in near if c != v and c not in near[v] and near[v] & near[c])
        out |= {(v, c, -n, i + 1) for i, (n, c) in enumerate(found[:k])}
    return out


def test_recommendations_equal_those_of_all_pairs(spark):
    r = random.Random(8)
    hubs = [(h, v) for h in range(4) for v in range(10, 60) if r.random() < 0.6]
    few = [(r.randrange(10, 60), r.randrange(60, 75)) for _ in range(60)] + [(0, 1), (10, 11), (100, 101)]
    pairs = sorted({*hubs, *few})
    got = structure.recommend(spark.createDataFrame(pairs, "src long, dst long")).collect()
    assert {tuple(x) for x in got} == _recommended(pairs, 3) and len(got) == len(_recommended(pairs, 3))


def test_recommendations_around_a_hub_do_not_pair_all_its_neighbours(spark, monkeypatch):
    n, most, plain = 400, [], structure.cut

    def cut(df):
        out = plain(df)
        most.append(out.count())
        return out

    monkeypatch.setattr(structure, "cut", cut)
    pairs = [(0, v) for v in range(1, n)] + [(v, v + n) for v in range(1, n)]  # no two of the hub's neighbours are alike
    got = structure.recommend(spark.createDataFrame(pairs, "src long, dst long"))
    assert got.where("vid = 399").count() == 3 and len(most) > 1 and max(most) < 10 * n


def test_cliques_need_no_pairs_of_a_hubs_neighbours(spark):
    n = 60
    pairs = spark.createDataFrame([(0, v) for v in range(1, n)] + [(1, 2), (2, 3), (1, 3)], "src long, dst long")
    found = structure.maximal_cliques(pairs)
    assert {tuple(map(int, r.members.split(","))) for r in found.collect()} == {(0, 1, 2, 3)} | {(0, v) for v in range(4, n)}
    # links among neighbours come of triangles: no join of a vertex's edges with each other
    assert "FlatMapGroupsInArrow" in found._jdf.queryExecution().optimizedPlan().toString()


def _cliques(pairs):
    near = {}
    for a, b in pairs:
        near.setdefault(a, set()).add(b)
        near.setdefault(b, set()).add(a)
    out, left = set(), [(frozenset(), frozenset(near), frozenset())]
    while left:
        members, open_, closed = left.pop()
        if not open_ and not closed:
            out.add(",".join(map(str, sorted(members))))
        for v in sorted(open_):
            left.append((members | {v}, open_ & near[v], closed & near[v]))
            open_, closed = open_ - {v}, closed | {v}
    return out


def test_cliques_of_a_dense_group_need_no_row_for_each_triangle(spark, monkeypatch):
    def triangles(*_):
        raise AssertionError("a row for each triangle of a group of near vectors")

    monkeypatch.setattr(structure, "triangles", triangles)
    r = random.Random(2)
    alike = list(combinations(range(200, 320), 2))
    pairs = [p for p in combinations(range(30), 2) if r.random() < 0.5] + [(v, v + 200) for v in range(30)]
    want = _cliques(pairs) | {",".join(map(str, range(200, 320)))}
    for block in (structure.BLOCK, 200):  # one block for each partition or two, then many
        monkeypatch.setattr(structure, "BLOCK", block)
        got = structure.maximal_cliques(spark.createDataFrame(pairs + alike, "src long, dst long")).collect()
        assert {x.members for x in got} == want and len(got) == len(want) and all(x.size == x.members.count(",") + 1 for x in got)
