"""Pairs that are counted and not made."""

import random
from itertools import combinations

import pytest

from nestdep.operators import bruteforce, functional, overlap, results
from nestdep.operators.overlap_counts import mask_counts
from nestdep.plans import cells as plans

PATHS = ["$.a", "$.b[*]", "$.c[*]"]


def docs_of(spark, seed, n=30):
    rng = random.Random(seed)
    rows = [(i, rng.choice([None, 0, 1, 2]), [rng.randint(0, 5) for _ in range(rng.randint(0, 4))], [rng.randint(0, 4) for _ in range(rng.randint(0, 3))]) for i in range(n)]
    return spark.createDataFrame(rows, "id long, a int, b array<int>, c array<int>"), rows


def plain(rows):
    sets = [[set() if r[1] is None else {r[1]}, set(r[2]), set(r[3])] for r in rows]
    hist = {}
    for x, y in combinations(sets, 2):
        m = sum(1 << i for i in range(3) if x[i] & y[i])
        hist[m] = hist.get(m, 0) + 1
    return hist


def test_counted_masks_equal_all_pairs(spark):
    """Sets by their subsets, and large ones by the sets they meet."""
    df, rows = docs_of(spark, 1)
    want = {m: n for m, n in plain(rows).items() if m}
    for small in ((10,), (1,)):
        assert mask_counts(plans.unroll_dynamic(df, "id", PATHS), 3, small) == want


def test_more_pairs_than_the_limit_give_the_same(spark, monkeypatch):
    df, rows = docs_of(spark, 2)
    cells = plans.unroll_dynamic(df, "id", PATHS)
    want = [functional.mine_functional(df, "id", paths=PATHS).collect(), overlap.overlap_holds(cells, [1], 0).collect()]
    violating = functional.count_violations(df, "id", ["$.b[*]"], ["$.a", "$.c[*]"]).collect()
    monkeypatch.setattr(overlap, "PAIR_LIMIT", 3)
    assert functional.mask_histogram(df, "id", PATHS)[0] == plain(rows)
    assert [functional.mine_functional(df, "id", paths=PATHS).collect(), overlap.overlap_holds(cells, [1], 0).collect()] == want
    assert functional.count_violations(df, "id", ["$.b[*]"], ["$.a", "$.c[*]"], limit=3).collect() == violating


def test_validated_miner_beyond_the_limit_of_pairs(spark, monkeypatch):
    """Single-valued paths of which most pairs share a value, as customers' segments and nations."""
    rows = [(i, i % 3, i % 8, i % 8 // 4) for i in range(80)]
    df = spark.createDataFrame(rows, "id long, segment int, nation int, region int")
    paths = ["$.segment", "$.nation", "$.region"]
    want = functional.mine_functional(df, "id", paths=paths, max_lhs=2).collect()
    monkeypatch.setattr(overlap, "PAIR_LIMIT", 3)
    assert functional.mine_validated(df, "id", paths, 2, sample=0.5)[0].collect() == want
    assert [(r["lhs"], r["rhs"]) for r in want] == [("$.nation", "$.region")]


@pytest.mark.parametrize("sample", [1.0, 0.1])
def test_validated_miner_of_more_pairs_than_any_default_limit(spark, sample):
    """72 million pairs share a value: in the sample, or where the one violating pair is looked for (no extreme of its group is in it)."""
    y = "CASE id WHEN 0 THEN array(1, 4) WHEN 1 THEN array(2, 5) WHEN 2 THEN array(4, 5) ELSE array(0, 4, 5) END"
    df = spark.range(12_000).selectExpr("id", "0 as x", f"{y} as y")
    assert df.where("id < 2").where(functional.hash_sample("id")(0, 0.1)).count() < 2
    found = functional.mine_validated(df, "id", ["$.x", "$.y[*]"], 2, sample=sample)[0].collect()
    assert [(r["lhs"], r["rhs"]) for r in found] == [("", "$.x")]


def test_validated_miner_of_more_right_sides_than_the_limit(spark):
    """Any two right sides overlap, but no value is in all of them: 13,000 would be compared with a third of them."""
    y = "array(id % 3, (id + 1) % 3, id + 3)"
    df = spark.range(13_000).selectExpr("id", "id % 2 as x", f"{y} as y")
    found = functional.mine_validated(df, "id", ["$.x", "$.y[*]"], 2, sample=0.01)[0].collect()
    assert [(r["lhs"], r["rhs"]) for r in found] == [("", "$.y[*]")]
    with pytest.raises(plans.TooLarge):
        functional.mine_validated(df, "id", ["$.x", "$.y[*]"], 2, sample=0.01, limit=overlap.PAIR_LIMIT)


def test_errors_and_strengths_of_groups_equal_those_of_pairs(spark):
    rng = random.Random(3)
    rows = [(i, rng.randint(0, 2), rng.choice([None, 0, 1, 2, 3])) for i in range(40)]
    df = spark.createDataFrame(rows, "id long, x int, y int")
    error = lambda **o: functional.nfd_error(df, "id", ["$.x"], ["$.y"], **o).collect()
    assert error(limit=3) == error()
    names = df.selectExpr("id", "x", "id as y")  # all differ: every order of pairs takes half of each group
    strength = lambda **o: functional.nfd_strength(names, "id", ["$.x"], ["$.y"], **o).collect()
    assert strength(limit=3) == strength()


def test_brute_force_compares_equal_documents_once(spark):
    rows = [(i, i % 3, [i % 2, 7], [i % 5 if i % 4 else i]) for i in range(60)]
    df = spark.createDataFrame(rows, "id long, a int, b array<int>, c array<int>")
    found = {tuple(r) for r in functional.mine_functional(df, "id", "negative_cover", paths=PATHS).collect()}
    assert {tuple(r) for r in bruteforce.bruteforce_nfds(df, "id", PATHS, limit=40).collect()} == found


def test_brute_force_inclusion_has_no_limit_of_its_own(spark):
    df = spark.range(200_001).selectExpr("id", "id as x")
    assert [r["valid"] for r in bruteforce.bruteforce_ninds(df, "id", paths=["$.id", "$.x"]).collect()] == [True, True]


def test_many_subsets_of_few_pairs_are_compared(spark):
    """Ten values on each of two paths: a million subsets a document, but only nine documents on each side that it meets."""
    df = spark.range(90).selectExpr("id", "sequence(id, id + 9) as b", "sequence(id, id + 9) as c")
    cells = plans.unroll_dynamic(df, "id", ["$.b[*]", "$.c[*]"])
    found = {}

    def count():
        found.update(mask_counts(cells, 2))
        return spark.range(1)

    assert results.time_run(count, 1, 60)["status"] == "ok"
    assert found == {3: sum(90 - k for k in range(1, 10))}


@pytest.mark.parametrize("options", [{}, {"method": "negative_cover", "pooling": "per_mask"}, {"order": "affine", "theta": 0.6}])
def test_approximate_miners_beyond_the_limit_of_pairs(spark, options):
    """72 million pairs share their only x: bounds decide most candidates, covers of few pairs the others."""
    df = spark.range(12_000).selectExpr("id", "0 as x", "id div 2 as y", "array(id div 4, IF(id % 40 = 0, -1, id div 3)) as z")
    few = df.where("id < 120")
    mine = lambda d, **o: functional.mine_functional(d, "id", **({"theta": 0.9, "max_lhs": 2, "paths": ["$.x", "$.y", "$.z[*]"]} | options | o))
    found = {(r["lhs"], r["rhs"]) for r in mine(df).collect()}
    assert ("", "$.x") in found and ("$.y", "$.z[*]") in found and ("$.x", "$.y") not in found
    with pytest.raises(plans.TooLarge):
        mine(df, limit=overlap.PAIR_LIMIT).collect()
    want = mine(few).collect()
    with pytest.MonkeyPatch.context() as patch:
        patch.setattr(functional, "PAIR_LIMIT", 7_000)  # 7,140 pairs share x
        patch.setattr(overlap, "PAIR_LIMIT", 7_000)
        assert mine(few).collect() == want


@pytest.mark.parametrize("limit", [100, 3_000])
def test_strengths_of_more_pairs_than_the_limit(spark, monkeypatch, limit):
    """Slices of the order give the same covers as all pairs at once."""
    df, _ = docs_of(spark, 4, 90)
    cells = plans.unroll_dynamic(df, "id", PATHS)
    candidates = [(x, a) for x in range(1, 8) for a in range(3) if not x >> a & 1]
    want = functional.strengths(cells, 3, candidates, 90)
    assert len({round(s, 2) for s in want.values()}) > 3
    monkeypatch.setattr(functional, "PAIR_LIMIT", limit)
    monkeypatch.setattr(functional, "candidate_strengths", None)
    assert functional.strengths(cells, 3, candidates, 90) == want
