import random
from itertools import combinations, permutations, product

import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from nestdep.operators import cover, functional, inclusion, lattice, overlap
from nestdep.plans import cells as plans
from nestdep.queries import approximation_example, reference_example

MASKS = st.dictionaries(st.integers(0, 31), st.integers(1, 3), max_size=12)


@given(MASKS)
@settings(max_examples=150, deadline=None)
def test_levelwise_negative_cover_and_brute_force_agree(hist):
    found = lattice.levelwise(hist, 5, 3)
    assert found == lattice.invert(lattice.negative_cover(hist, 5), 5, 3) == lattice.brute_force(hist, 5, 3)


@given(MASKS, st.integers(0, 31), st.integers(0, 31), st.integers(0, 31))
@settings(max_examples=150, deadline=None)
def test_axioms(hist, x, y, z):
    holds = lambda a, b: all(m & b == b for m in hist if m & a == a)
    assert holds(x | y, x)
    if holds(x, y):
        assert holds(x | z, y | z)
        if holds(y, z):
            assert holds(x, z) and holds(x, y | z)


def test_inference():
    fs = frozenset
    deps = [(fs("a"), "b"), (fs("b"), "c"), (fs("a"), "c"), (fs("ab"), "d")]
    assert lattice.attr_closure("a", deps) == set("abcd")
    assert lattice.implies(deps, (fs("a"), "d")) and not lattice.implies(deps, (fs("c"), "a"))
    small = lattice.minimal_cover(deps)
    assert small == {(fs("a"), "b"), (fs("b"), "c"), (fs("a"), "d")} and lattice.equivalent(small, deps)
    assert inclusion.nind_closure([("a", "b"), ("b", "c")]) == {("a", "b"), ("b", "c"), ("a", "c")}
    assert inclusion.nind_reduce([("a", "b"), ("b", "c"), ("a", "c")]) == {("a", "b"), ("b", "c")}


@given(st.lists(st.tuples(st.integers(0, 7), st.integers(0, 7)), max_size=12))
@settings(max_examples=100, deadline=None)
def test_matching_bounds_the_exact_cover(edges):
    edges = sorted({tuple(sorted(e)) for e in edges if e[0] != e[1]})
    best = cover.exact_cover(edges)
    assert all(set(e) & best for e in edges)
    assert not any(all(set(e) & set(c) for e in edges) for c in combinations(range(8), max(0, len(best) - 1))) or not best
    greedy = cover.sequential_cover(edges)
    assert len(greedy) // 2 <= len(best) <= len(greedy)


def test_greedy_rounds_equal_the_scan(spark):
    rng = random.Random(4)
    for _ in range(3):
        edges = sorted({tuple(sorted(rng.sample(range(25), 2))) for _ in range(40)})
        got = cover.greedy_cover(spark.createDataFrame(edges, "d1 long, d2 long"))
        assert {r[0] for r in got.collect()} == set(cover.sequential_cover(edges))


def test_worked_approximation(spark):
    df = approximation_example(spark)
    pairs = {tuple(r) for r in functional.nfd_violations(df, "doc_id", ["$.a[*]"], ["$.b[*]"]).collect()}
    assert pairs == {(1, 4), (2, 3), (3, 4)}
    assert len(cover.exact_cover(pairs)) == 2
    # The two edges (2, 3), (3, 4) alone give a greedy cover of two documents of four.
    assert cover.cover_strength(spark.createDataFrame([(2, 3), (3, 4)], "d1 long, d2 long"), 4).first()["strength"] == 0.5
    assert functional.nfd_violations(df, "doc_id", ["$.b[*]"], ["$.a[*]"]).count() == 0


def test_self_pairs_and_missing_sides(spark):
    df = reference_example(spark)
    check = lambda x, y, **o: {tuple(r) for r in functional.nfd_violations(df, "id", [x], [y], **o).collect()}
    assert check("$.id", "$.parent") == set()
    assert check("$.id", "$.parent", self_pairs=True) == {(3, 3), (5, 5)}
    assert check("$.id", "$.rel[*]", self_pairs=True) == {(5, 5)}
    assert check("$.types[*]", "$.main") == {(2, 4), (4, 5)}
    two = spark.createDataFrame([(1, 1, None), (2, 1, 2)], "id long, x int, y int")
    assert functional.nfd_violations(two, "id", ["$.x"], ["$.y"]).count() == 1
    assert functional.nfd_violations(two, "id", ["$.x"], ["$.y"], missing_rhs="ignores").count() == 0
    with pytest.raises(ValueError):
        functional.mine_functional(two, "id", missing_rhs="ignores")


def random_docs(spark, seed, n=12):
    rng = random.Random(seed)
    pick = lambda: [rng.randint(0, 3) for _ in range(rng.randint(0, 2))]
    rows = [(i, rng.choice([None, 0, 1, 2]), pick(), pick()) for i in range(n)]
    return spark.createDataFrame(rows, "id long, a int, b array<int>, c array<int>"), rows


def sets_of(row):
    return [set() if row[1] is None else {row[1]}, set(row[2]), set(row[3])]


@pytest.mark.parametrize("seed", range(3))
def test_miners_against_the_definition(spark, seed):
    df, rows = random_docs(spark, seed)
    paths = ["$.a", "$.b[*]", "$.c[*]"]
    docs = [sets_of(r) for r in rows]
    values = [set().union(*(d[i] for d in docs)) for i in range(3)]
    want = {(paths[i], paths[j]) for i in range(3) for j in range(3) if i != j and values[i] and values[j] and values[i] <= values[j]}
    for method, unrolling in product(("inverted", "sorted"), ("dynamic", "static")):
        got = inclusion.mine_inclusion(df, "id", method, paths=paths, unrolling=unrolling).where("valid").select("lhs", "rhs").collect()
        assert {tuple(r) for r in got} == want, (method, unrolling)
    hist: dict[int, int] = {}
    for x, y in combinations(docs, 2):
        m = sum(1 << i for i in range(3) if x[i] & y[i])
        hist[m] = hist.get(m, 0) + 1
    assert functional.mask_histogram(df, "id", paths)[0] == hist
    for lhs, rhs in [(["$.a"], "$.b[*]"), (["$.b[*]"], "$.a"), (["$.b[*]", "$.c[*]"], "$.a"), (["$.a"], "$.c[*]")]:
        linear = functional.validate_nfd(df, "id", lhs, rhs).first()["holds"]
        assert linear == (functional.nfd_violations(df, "id", lhs, [rhs]).count() == 0)
    bitmaps = overlap.adjacency_bitmaps(plans.unroll_dynamic(df, "id", paths))
    for lhs, rhs in (([0], 1), ([1], 2), ([1, 2], 0)):
        x = sum(1 << p for p in lhs)
        assert overlap.bitmap_holds(bitmaps, lhs, rhs).first()["holds"] == (lattice.violations(hist, x, rhs) == 0)


def test_validated_mining_equals_full_mining(spark):
    df, _ = random_docs(spark, 11, 30)
    paths = ["$.a", "$.b[*]", "$.c[*]"]
    full = {(r["lhs"], r["rhs"]) for r in functional.mine_functional(df, "id", paths=paths, max_lhs=2).collect()}
    looped, rounds = functional.mine_validated(df, "id", paths, 2, sample=0.2)
    assert {(r["lhs"], r["rhs"]) for r in looped.collect()} == full and rounds >= 1


def test_pairwise_overlap_without_common_value(spark):
    df = spark.createDataFrame([(1, 0, [1, 2]), (2, 0, [2, 3]), (3, 0, [1, 3])], "id long, x int, y array<int>")
    assert functional.validate_nfd(df, "id", ["$.x"], "$.y[*]").first()["holds"]


def test_threshold_is_monotone(spark, sf_dir):
    from nestdep.sources.collections import build_collection

    df = build_collection("order_docs", spark, sf_dir)
    paths = ["$.status", "$.flags[*]", "$.items[*].suppkey", "$.items[*].partkey", "$.custkey"]
    valid = lambda t: {tuple(r) for r in inclusion.mine_inclusion(df, "orderkey", theta=t, paths=paths).where("valid").select("lhs", "rhs").collect()}
    assert valid(1.0) <= valid(0.9) <= valid(0.3)


def test_pairs_are_refused_beyond_the_limit(spark):
    df = spark.range(200).selectExpr("id", "1 as x", "2 as y")
    with pytest.raises(plans.TooLarge):
        functional.mine_functional(df, "id", limit=1000)


def test_array_elements_lose_their_pairing(spark):
    """Static rows keep the pairing within an array of objects, dynamic sets do not."""
    item = "array<struct<p:string,s:string>>"
    df = spark.createDataFrame([(1, [("p1", "s1"), ("p2", "s2")], 10), (2, [("p1", "s2"), ("p3", "s9")], 20)], f"id long, items {item}, o int")
    assert not functional.validate_nfd(df, "id", ["$.items[*].p", "$.items[*].s"], "$.o").first()["holds"]
    flat = plans.unroll_static(df).toDF("id", "p", "s", "o")
    assert functional.fd_holds(flat, ["p", "s"], "o").first()["holds"]


def test_sampled_theory_is_implied_by_fewer_pairs(spark):
    df, _ = random_docs(spark, 5, 40)
    paths = ["$.a", "$.b[*]", "$.c[*]"]
    full = [(frozenset(r["lhs"].split(",")) - {""}, r["rhs"]) for r in functional.mine_functional(df, "id", paths=paths).collect()]
    some = [(frozenset(r["lhs"].split(",")) - {""}, r["rhs"]) for r in functional.mine_functional_sampled(df, "id", 2, 0.3, paths=paths).collect()]
    assert all(lattice.implies(some, d) for d in full)


def test_approximate_miners_test_empty_left_sides(spark):
    rows = [(i, "x" if i else "y", [i, i + 1], [[1, 2], [2, 3], [1, 3]][i % 3]) for i in range(20)]
    df = spark.createDataFrame(rows, "id long, a string, b array<int>, c array<int>")
    exact = {("", "$.c[*]")}
    want = {("", "$.c[*]"): 1.0, ("", "$.a"): 0.95}
    deps = lambda **o: {(r["lhs"].strip("{}"), r["rhs"]): r["strength"] for r in functional.mine_functional(df, "id", paths=["$.a", "$.b[*]", "$.c[*]"], **o).collect()}
    assert exact <= set(deps())
    for options in ({}, {"method": "negative_cover", "pooling": "per_mask"}):
        got = deps(theta=0.85, **options)
        assert {k: v for k, v in got.items() if k[1] != "$.b[*]"} == want
        assert ("", "$.b[*]") not in got


def plain_nary(rows, arity, theta):
    """All pairs of sequences of columns, straight from the definition; rows hold sets."""
    width, out = len(rows[0]), {}
    at = lambda x: {t for r in rows for t in product(*(r[p] for p in x))}
    for x in combinations(range(width), arity):
        for y in permutations(range(width), arity):
            left, right = at(x), at(y)
            if x != y and left:
                out[x, y] = (len(left), len(left & right), len(left & right) >= theta * len(left))
    return out


@pytest.mark.parametrize("alignment", ["product", "element"])
@pytest.mark.parametrize("seed", range(4))
def test_nary_against_the_definition(spark, alignment, seed):
    rng = random.Random(seed)
    missing = seed % 2  # pruning is used only where nothing is missing
    pick = lambda: rng.choice([None, "p", "q", "r"]) if missing else rng.choice("pqr")
    names = "abcd"
    if alignment == "element":
        items = [[tuple(pick() for _ in names) for _ in range(rng.randint(1, 3))] for _ in range(5)]
        df = spark.createDataFrame([(i, x) for i, x in enumerate(items)], "id long, it array<struct<a:string,b:string,c:string,d:string>>")
        paths, plain = [f"$.it[*].{n}" for n in names], [[{v} - {None} for v in e] for x in items for e in x]
    else:
        sets = [[[v for v in (pick() for _ in range(rng.randint(1, 2))) if v] for _ in names] for _ in range(5)]
        df = spark.createDataFrame([(i, *x) for i, x in enumerate(sets)], "id long, a array<string>, b array<string>, c array<string>, d array<string>")
        paths, plain = [f"$.{n}[*]" for n in names], [[set(v) for v in x] for x in sets]
    number = {p: i for i, p in enumerate(paths)}
    side = lambda t: tuple(number[p] for p in t.split(","))
    for theta in (1.0, 0.8):
        got = {(side(r["lhs"]), side(r["rhs"])): (r["support"], r["included"], r["valid"]) for r in inclusion.mine_inclusion_nary(df, "id", 3, theta, paths, alignment).collect()}
        for arity in (2, 3):
            want = plain_nary(plain, arity, theta)
            mine = {k: v for k, v in got.items() if len(k[0]) == arity}
            assert all(want[k] == v for k, v in mine.items())
            assert {k for k, v in mine.items() if v[2]} == {k for k, v in want.items() if v[2]}
            if theta < 1 or missing:
                assert mine == want


def test_nary_keeps_identical_prefixes(spark):
    """(a, b, c) in (a, b, d) where a and b are unique and c equals d."""
    df = spark.createDataFrame([(i, f"a{i}", f"b{i}", f"c{i % 3}", f"c{i % 3}") for i in range(9)], "id long, a string, b string, c string, d string")
    got = {(r["lhs"], r["rhs"]) for r in inclusion.mine_inclusion_nary(df, "id", 3, 1.0, ["$.a", "$.b", "$.c", "$.d"]).where("valid").collect()}
    assert ("$.a,$.b,$.c", "$.a,$.b,$.d") in got


def test_nary_at_a_threshold_needs_no_strong_part(spark):
    rows = [(i, f"x{i}", "k") if i < 10 else (i, "y0", f"z{i}") for i in range(100)]
    more = [(100 + i, f"w{i}", f"z{i}") for i in range(10, 100)]
    df = spark.createDataFrame([(*r, r[1] if r[1] == "y0" else f"n{r[0]}", r[2]) for r in rows] + [(*r, "y0", r[2]) for r in more], "id long, a string, b string, c string, d string")
    got = {(r["lhs"], r["rhs"]): r for r in inclusion.mine_inclusion_nary(df, "id", 2, 0.4, ["$.a", "$.b", "$.c", "$.d"]).collect()}
    one = got["$.a,$.b", "$.c,$.d"]
    assert (one["support"], one["included"], one["valid"]) == (190, 90, True)


@pytest.mark.parametrize("theta", [1.0, 0.7, 0.3])
def test_sorted_miner_equals_the_inverted_one(spark, theta):
    rng = random.Random(int(theta * 10))
    rows = [(i, *([rng.randint(0, 5 * (k + 1)) for _ in range(rng.randint(0, 3))] for k in range(4))) for i in range(60)]
    df = spark.createDataFrame(rows, "id long, a array<int>, b array<int>, c array<int>, d array<int>")
    paths = [f"$.{n}[*]" for n in "abcd"]
    cells = plans.unroll_dynamic(df, "id", paths)
    for rounds in ((1,), (2, 18, 80), (1, 1, 1, 1)):
        found, seen = inclusion.sorted_rounds(cells, paths, theta, rounds)
        want = inclusion.mine_inclusion(df, "id", theta=theta, paths=paths).where("valid")
        assert sorted(map(tuple, found.collect())) == sorted(map(tuple, want.collect()))
        assert all(x["candidates"] >= y["candidates"] for x, y in zip(seen, seen[1:]))


def test_sorted_rounds_read_distinct_values(spark):
    """Values that many tasks hold are stored once for each path, not once a task."""
    rows = [(i, [f"v{i % 5}"], [f"v{i % 3}"]) for i in range(64)]
    df = spark.createDataFrame(rows, "id long, a array<string>, b array<string>").repartition(8)
    paths = ["$.a[*]", "$.b[*]"]
    _, seen = inclusion.sorted_rounds(plans.unroll_dynamic(df, "id", paths), paths, 0.5, (1,))
    assert [s["cells"] for s in seen] == [8]


def test_merge_counts_runs_across_batches_and_words(spark):
    """More than 62 paths, runs that cross Arrow batches."""
    rows = [(p, f"n{v}") for v in range(300) for p in range(70) if (v + p) % 3]
    cells = spark.createDataFrame(rows, "path_id int, value string")
    spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", "7")
    try:
        key = lambda df: sorted(map(tuple, df.select("m0", "m1", "n_values").collect()))
        assert key(inclusion.merged_signatures(cells, 70)) == key(inclusion.signatures(inclusion.value_masks(cells, 70), 70))
    finally:
        spark.conf.unset("spark.sql.execution.arrow.maxRecordsPerBatch")


def test_registered_metadata(spark):
    df, _ = random_docs(spark, 3)
    paths = ["$.a", "$.b[*]", "$.c[*]"]
    assert {"values", "overlaps", "bitmaps"} <= set(plans.METADATA)
    masks = plans.build_metadata("values", df, "id", paths)
    assert sorted(map(tuple, masks.collect())) == sorted(map(tuple, inclusion.value_masks(plans.unroll_dynamic(df, "id", paths), 3).collect()))


def test_hot_values_are_salted(spark, monkeypatch):
    df, _ = random_docs(spark, 7, 40)
    cells = plans.unroll_dynamic(df, "id", ["$.a", "$.b[*]", "$.c[*]"])
    plain = sorted(map(tuple, overlap.overlap_masks(cells).collect()))
    monkeypatch.setattr(overlap, "HOT", 2)
    assert sorted(map(tuple, overlap.overlap_masks(cells).collect())) == plain and plain
    with pytest.raises(plans.TooLarge):
        overlap.adjacency_bitmaps(cells, limit=3)


@given(st.lists(st.tuples(st.integers(0, 1), st.sets(st.integers(0, 4), max_size=3)), min_size=1, max_size=7))
@settings(max_examples=15, deadline=None)
def test_linear_validation_against_the_definition(spark, docs):
    df = spark.createDataFrame([(i, x, sorted(y)) for i, (x, y) in enumerate(docs)], "id long, x int, y array<int>")
    want = not any(a[0] == b[0] and not a[1] & b[1] for a, b in combinations(docs, 2))
    assert functional.validate_nfd(df, "id", ["$.x"], "$.y[*]").first()["holds"] == want


def test_strengths_known_from_the_histogram_make_no_edges(spark):
    df, rows = random_docs(spark, 9, 14)
    paths = ["$.a", "$.b[*]", "$.c[*]"]
    masks = overlap.overlap_masks(plans.unroll_dynamic(df, "id", paths))
    every = [(x, a) for x in range(1, 8) for a in range(3) if not x >> a & 1]
    found = functional.candidate_strengths(masks, every, len(rows), "lex")
    pairs = [tuple(r) for r in masks.orderBy("d1", "d2").collect()]
    for x, a in every:
        edges = [(i, j) for i, j, m in pairs if m & x == x and not m >> a & 1]
        assert found[x, a] == pytest.approx(1 - len(cover.sequential_cover(edges)) / len(rows))


def test_static_miners_agree_on_nested_documents(spark, sf_dir):
    from nestdep.sources.collections import build_collection

    df = build_collection("conversation_docs", spark, sf_dir)
    one, two = ({(r["lhs"], r["rhs"]) for r in functional.mine_functional(df, "conv_id", m, unrolling="static", max_lhs=2).collect()} for m in ("levelwise", "negative_cover"))
    assert one == two and one
