"""Operators over the whole corpus: neighbours, mixing, archives, near-duplicates, passages, the pipeline."""

import collections
import hashlib
import re

import numpy as np
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

from nestdep.llm import mixing, near_dedup, neighbours, queries, substring_dedup, warc
from nestdep.llm._text import words_of

from ..conftest import rows_of

WORD = re.compile(r"[^\x20\x09-\x0D]+")


@pytest.mark.parametrize("name", sorted(queries.SQL))
def test_queries_with_sql(spark, sf_dir, duck, name):
    assert rows_of(queries.QUERIES[name](spark, sf_dir).toPandas()) == rows_of(duck.sql(queries.SQL[name]).df())


def test_op2_recall_and_order(spark, sf_dir):
    got = queries.op2_neighbours(spark, sf_dir).toPandas()
    rows = spark.read.parquet(f"{sf_dir}/embeddings.parquet").collect()
    ids, x = np.array([r["vec_id"] for r in rows]), np.array([r["embedding"] for r in rows], dtype=np.float64)
    hits = total = 0
    for i in np.flatnonzero(ids % 100 == 0):
        d = np.sqrt(((x - x[i]) ** 2).sum(axis=1))
        d[i] = np.inf
        best = np.lexsort((ids, d))[:10]
        mine = got[got.query_id == ids[i]].sort_values("rank")
        assert mine["rank"].tolist() == list(range(1, 11))
        assert np.allclose(mine["score"], [d[np.flatnonzero(ids == v)[0]] for v in mine["vec_id"]], atol=1e-12)
        hits += len(set(mine["vec_id"]) & set(ids[best].tolist()))
        total += 10
    assert hits / total >= 0.9


def test_neighbours_ties_and_unusable_vectors(spark):
    v = lambda *x: [float(y) for y in x]
    rows = [(i, v(1, 0, 0, 1)) for i in range(1, 30)] + [(0, v(1, 0, 0, 1)), (100, None), (101, v(0, 0, 0, 0)), (102, [1.0, None, 0.0, 0.0]), (103, v(float("nan"), 1, 1, 1)), (104, v(1, 1)), (None, v(1, 1, 1, 1)), (200, v(2, 0, 0, 2))]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<double>")
    got = neighbours.nearest(df, F.col("vec_id") % 100 == 0, k=10).orderBy("query_id", "rank").collect()
    assert [r["vec_id"] for r in got if r["query_id"] == 0] == list(range(1, 11))
    assert [r["vec_id"] for r in got if r["query_id"] == 200] == list(range(0, 10)) and {r["query_id"] for r in got} == {0, 200}
    few = spark.createDataFrame([(0, v(1, 2)), (1, v(2, 1)), (2, v(1, 1))], "vec_id long, embedding array<double>")
    assert [r["vec_id"] for r in neighbours.nearest(few, F.col("vec_id") == 0).orderBy("rank").collect()] == [2, 1]
    assert neighbours.nearest(few.where("vec_id < 0"), F.col("vec_id") == 0).count() == 0


def test_anisotropic_codes_keep_the_parallel_part():
    rng = np.random.default_rng(0)
    x = rng.normal(size=(2000, 16))
    x /= np.linalg.norm(x, axis=1, keepdims=True)
    aware, plain = neighbours.Quantiser(x, 0.5), neighbours.Quantiser(x, 0.0)

    def along(m):
        codes = m.encode(m.pad(x))
        back = np.concatenate([m.books[s][codes[:, s]] for s in range(m.parts)], axis=1)
        return np.abs(((x - back) * x).sum(axis=1)).mean()

    assert along(aware) < along(plain)


def test_targets_reshare_the_excess():
    got = mixing.source_targets([("b", 100), ("a", 1000), (None, 10), ("c", 50)])
    assert [s for s, _, _ in got] == ["a", "b", "c", None]
    assert abs(sum(t for _, _, t in got) - 1.5 * 1160) < 1e-9 and all(t <= 2 * n + 1e-9 for _, n, t in got)
    assert got[1][2] == 200 and got[3][2] == 20


def test_splitting_tree_deals_each_draw_once(spark):
    quotas = [37, 5, 0, 120]
    seen = collections.Counter((r["sidx"], r["draw"]) for r in mixing.shard_shares(spark, quotas, 7, 3).collect())
    assert seen == {(s, d): 1 for s, q in enumerate(quotas) for d in range(q)}
    sizes = collections.Counter(r["shard"] for r in mixing.shard_shares(spark, quotas, 7, 3).collect())
    assert max(sizes.values()) - min(sizes.values()) <= 3


def test_op3(spark, sf_dir, odd_docs, no_docs):
    got = queries.op3_mix(spark, sf_dir).toPandas()
    docs = {r["doc_id"]: r for r in spark.read.parquet(f"{sf_dir}/documents.parquet").collect()}
    assert len(got) == len(docs)
    size = {i: len(WORD.findall(r["text"] or "")) for i, r in docs.items()}
    total = collections.Counter()
    for i, r in docs.items():
        total[r["source"]] += size[i]
    want = {s: t for s, _, t in mixing.source_targets(list(total.items()))}
    for r in got.itertuples():
        assert r.size == size[r.doc_id] and r.source_size == total[r.source] and abs(r.target - want[r.source]) < 1e-6 and 0 <= r.taken <= 2 * r.size
    for s, part in got.groupby("source"):
        assert abs(part["taken"].sum() - want[s]) <= 1
    assert rows_of(got.drop(columns="shards")) == rows_of(queries.op3_mix(spark, sf_dir).toPandas().drop(columns="shards"))
    # Small blocks and shards: the same totals through a real tree.
    small = mixing.plan_mix(spark.read.parquet(f"{sf_dir}/documents.parquet"), block_words=200, shard_words=3000).toPandas()
    assert sorted(zip(small["source"], small["taken"]))[0] is not None
    for s, part in small.groupby("source"):
        assert abs(part["taken"].sum() - want[s]) <= 1
    assert len({d["shard"] for x in small["draws"] for d in x}) > 3
    odd = mixing.plan_mix(odd_docs).toPandas()
    assert len(odd) == odd_docs.count() and (odd["taken"] <= 2 * odd["size"]).all()
    mixed = mixing.mixed_documents(odd_docs)
    assert mixed.columns == odd_docs.columns
    words = sum(len(WORD.findall(r["text"])) for r in mixed.collect())
    assert words == odd["taken"].sum()
    assert mixing.plan_mix(no_docs).count() == 0 and mixing.mixed_documents(no_docs).count() == 0


def test_many_sources_take_the_salted_way(spark, sf_dir, monkeypatch):
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    want = rows_of(mixing.plan_mix(docs).select("id", "taken").toPandas())
    monkeypatch.setattr(mixing, "MAX_BROADCAST", 2)
    assert rows_of(mixing.plan_mix(docs).select("id", "taken").toPandas()) == want


def test_warc_round_trip_and_random_access(spark, tmp_path, monkeypatch):
    monkeypatch.setattr(warc, "FRAME_BYTES", 3000)
    big, other = "x" * 1500, "ü" * 700
    rows = [(1, "http://a/ \n", big, "k"), (5, None, big, "k"), (3, "u", big, "k"), (2, "u", None, "k"), (4, "u", "", "k"), (6, "u", "small", "k"), (7, "u", "small", "k"), (None, "u", big, "k"), (8, "u", other, "k"), (8, "u", other, "k")]
    pages = spark.createDataFrame(rows, "page_id long, url string, html string, digest string")
    where = f"file://{tmp_path}/w"
    manifest = warc.write_archives(pages, where)
    got = sorted(((r["id"], r["record_type"], r["refers_to"], r["payload_bytes"]) for r in warc.read_archives(spark, where).collect()), key=str)
    want = [(1, "revisit", 5, 1500), (5, "response", None, 1500), (3, "revisit", 5, 1500), (2, "response", None, 0), (4, "response", None, 0), (6, "response", None, 5), (7, "response", None, 5), (None, "revisit", 5, 1500), (8, "response", None, 1400), (8, "response", None, 1400)]
    assert got == sorted(want, key=str)
    for m in manifest.collect():
        headers, payload = warc.read_record(where, m["bundle"], m["frame"], m["frame_offset"], m["length"])
        assert headers["WARC-Record-ID"] == f"<urn:nestdep:page:{m['record_id']}>"
        if headers["WARC-Type"] == "response":
            assert hashlib.sha1(payload).hexdigest() == headers["WARC-Payload-Digest"].split(":")[1]
    assert warc.write_archives(pages.where("page_id < 0"), f"file://{tmp_path}/none").count() == 0
    assert warc.read_archives(spark, f"file://{tmp_path}/none").count() == 0


def test_bundles_are_plain_zstandard_too(spark, tmp_path):
    import zstandard

    pages = spark.createDataFrame([(i, "u", f"page {i}") for i in range(20)], "page_id long, url string, html string")
    warc.write_archives(pages, f"file://{tmp_path}/w")
    text = b"".join(zstandard.ZstdDecompressor().stream_reader(f.open("rb"), read_across_frames=True).read() for f in (tmp_path / "w").glob("*.zst"))
    assert all(f"page {i}".encode() in text for i in range(20))


def bag(text):
    w = WORD.findall(text or "")
    return collections.Counter(tuple(w[k : k + 5]) for k in range(max(1, len(w) - 4))) if w else None


def jaccard(a, b):
    return sum((a & b).values()) / sum((a | b).values())


def classes(texts):
    """Smallest member of each text's component of links, by brute force."""
    bags_ = {i: bag(t) for i, t in texts.items()}
    holders = collections.defaultdict(list)
    for i, b in bags_.items():
        for s in b or ():
            holders[s].append(i)
    parent = {i: i for i in texts}

    def find(x):
        while parent[x] != x:
            x = parent[x]
        return x

    for x, y in {(a, b) for own in holders.values() for k, a in enumerate(own) for b in own[:k]}:
        if jaccard(bags_[x], bags_[y]) >= 0.8:
            a, b = find(x), find(y)
            parent[max(a, b)] = min(a, b)
    return {i: find(i) for i in texts}


@pytest.mark.parametrize("sf", ["sf0.001", "sf0.01"])
def test_op6(spark, sf_dir, sf):
    base = sf_dir.replace("sf0.001", sf)
    got = {r["doc_id"]: r for r in queries.op6_near_dedup(spark, base).collect()}
    texts = {r["doc_id"]: r["text"] for r in spark.read.parquet(f"{base}/documents.parquet").collect()}
    want = classes(texts)
    assert {i: r["class_id"] for i, r in got.items()} == want
    assert all(r["stays"] == (r["class_id"] == i) for i, r in got.items())


def chain(n=60, words=120, seed=1):
    """Texts that each differ a little from the one before: a long component of partly dissimilar members."""
    rng = np.random.default_rng(seed)
    now = [f"t{i}" for i in range(words)]
    out = []
    for k in range(n):
        out.append(" ".join(now))
        now[int(rng.integers(words))] = f"n{k}"
    return out


def test_near_copies_in_a_chain(spark, monkeypatch):
    monkeypatch.setattr(near_dedup, "CHUNK", 16)  # several blocks and visits for one bucket
    texts = dict(enumerate(chain()))
    df = spark.createDataFrame(list(texts.items()), "doc_id long, text string")
    assert {r["id"]: r["class_id"] for r in near_dedup.near_classes(df).collect()} == classes(texts)


def test_near_copies_odd_rows(spark, odd_docs, no_docs):
    rows = near_dedup.near_classes(odd_docs).collect()
    assert len(rows) == odd_docs.count()
    by = {r["id"]: r for r in rows}
    assert by[2]["class_id"] == 2 and by[3]["class_id"] == 3 and by[4]["class_id"] == 4 and by[1]["class_size"] == 2
    kept = near_dedup.drop_near_copies(odd_docs)
    assert kept.columns == odd_docs.columns and kept.where("doc_id = 1").count() == 1
    assert near_dedup.near_classes(no_docs).count() == 0 and near_dedup.drop_near_copies(no_docs).count() == 0


def test_signatures_estimate_weighted_similarity():
    a, b = "x y " * 30 + "a b c d e f g h", "x y " * 20 + "a b c d e f g z"
    words = words_of(pa.array([a, b], pa.large_string()))
    docs, hashes, weights = near_dedup.bags(words)
    sig = near_dedup.signatures(docs, hashes, weights, 2, 4000)
    assert abs((sig[0] == sig[1]).mean() - jaccard(bag(a), bag(b))) < 0.035
    assert near_dedup.overlaps(pa.array([a]), pa.array([b]))[0] == pytest.approx(jaccard(bag(a), bag(b)))


def test_components_both_ways(spark):
    rng = np.random.default_rng(2)
    edges = [(int(a), int(b)) for a, b in rng.integers(0, 60, size=(45, 2))]
    df = spark.createDataFrame(edges, "a long, b long")
    one = {r["node"]: r["root"] for r in near_dedup.components(df).collect()}
    two = {r["node"]: r["root"] for r in near_dedup.star_components(df).collect()}
    assert all(one[a] == one[b] for a, b in edges) and all(one[x] == two[x] for x in two)


def removed(texts, window=50):
    """(n_words, n_removed, kept) by brute force; texts in order of id."""
    first, words = {}, {i: WORD.findall(t or "") for i, t in texts}
    for i, _ in texts:
        for k in range(len(words[i]) - window + 1):
            first.setdefault(tuple(words[i][k : k + window]), i)
    out = {}
    for i, _ in texts:
        gone = set()
        for k in range(len(words[i]) - window + 1):
            if first[tuple(words[i][k : k + window])] < i:
                gone |= set(range(k, k + window))
        out[i] = len(words[i]), len(gone), " ".join(w for k, w in enumerate(words[i]) if k not in gone)
    return out


def test_passages_against_brute_force(spark):
    rng = np.random.default_rng(7)
    word = lambda: f"w{rng.integers(6)}"
    pool = [[word() for _ in range(30)] for _ in range(4)]
    texts = [(i, " ".join(w for k in rng.integers(4, size=rng.integers(0, 6)) for w in [*pool[k], word()])) for i in range(40)]
    df = spark.createDataFrame(texts, "doc_id long, text string")
    for window in (5, 12, 50):
        want = removed(texts, window)
        for r in substring_dedup.remove_repeated_passages(df, window=window).collect():
            assert (r["n_words"], r["n_removed"], r["kept_text"]) == want[r["doc_id"]]
            assert sum(s["end"] - s["start"] for s in r["spans"]) == r["n_removed"]


def test_passages_odd_rows(spark, odd_docs, no_docs):
    rows = collections.defaultdict(list)
    for r in substring_dedup.remove_repeated_passages(odd_docs).collect():
        rows[r["doc_id"]].append((r["n_words"], r["n_removed"]))
    assert rows[1] == [(7, 0), (7, 0)] and rows[2] == rows[3] == rows[4] == [(0, 0)]
    assert rows[6] == [(83, 0)] and rows[7] == [(82, 80)] and rows[None] == [(80, 80)]
    assert substring_dedup.remove_repeated_passages(no_docs).count() == 0


def test_pipeline(spark, sf_dir):
    import corpus_pipeline as p
    from nestdep.llm import bpe, pii, toxicity

    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    assert [n for n, _ in p.STAGES] == ["toxicity", "near_dedup", "pii", "mixing", "bpe"]
    net = toxicity.fit(docs, spark.read.parquet(f"{sf_dir}/labels.parquet"))
    scores = {r["doc_id"]: r["score"] for r in toxicity.score_toxicity(docs, net).collect()}
    clean = p.STAGES[0][1](spark, docs, sf_dir)
    assert clean.columns == docs.columns and {r["doc_id"] for r in clean.collect()} == {i for i, s in scores.items() if s < 0.7}
    texts = {r["doc_id"]: r["text"] for r in clean.collect()}
    one = p.STAGES[1][1](spark, clean, sf_dir)
    assert one.columns == docs.columns and {r["doc_id"] for r in one.collect()} == set(classes(texts).values())
    plain = p.STAGES[2][1](spark, one, sf_dir)
    assert plain.columns == docs.columns and {(r["doc_id"], r["text"]) for r in plain.collect()} == {(r["doc_id"], pii.redacted(r["text"])) for r in one.collect()}
    mixed = p.STAGES[3][1](spark, plain, sf_dir)
    assert mixed.columns == docs.columns
    taken = {r["id"]: r["taken"] for r in mixing.plan_mix(plain).collect()}
    words = collections.Counter()
    for r in mixed.collect():
        words[r["doc_id"]] += len(WORD.findall(r["text"]))
    assert words == {i: n for i, n in taken.items() if n}
    last = p.STAGES[4][1](spark, mixed, sf_dir)
    own = bpe.loaded(queries.vocabulary("word_bpe_49k.json"))
    want = collections.Counter((r["doc_id"], own.encode_batch([r["text"]])[0][1]) for r in mixed.collect())
    assert collections.Counter((r["doc_id"], bytes(r["token_ids"])) for r in last.collect()) == want


def test_pipeline_on_odd_and_empty_tables(spark, sf_dir, odd_docs, no_docs, tmp_path):
    """Nulls, blank and repeated rows, columns with the names operators use themselves, no rows at all."""
    import corpus_pipeline

    for k, docs in enumerate((odd_docs, no_docs)):
        now = docs
        for name, stage in corpus_pipeline.STAGES:
            out = stage(spark, now, sf_dir)
            if name != corpus_pipeline.STAGES[-1][0]:
                assert out.columns == docs.columns, name
            path = f"file://{tmp_path}/{k}-{name}"
            out.write.parquet(path)
            now = spark.read.parquet(path)
        rows = now.collect()
        assert bool(rows) == (k == 0)
        assert all(r["n_tokens"] * 4 == len(r["token_ids"]) for r in rows)


@pytest.mark.parametrize("limit", [400_000, 0])
def test_warc_pages_of_any_shape(spark, tmp_path, monkeypatch, limit):
    """Pages over one frame, no column of addresses, other columns with names of ours, digests told or joined."""
    monkeypatch.setattr(warc, "FRAME_BYTES", 5000)
    monkeypatch.setattr(warc, "BROADCAST_DIGESTS", limit)
    big = "é" * 20_000
    rows = [(1, big, "d"), (2, big, "x"), (3, "", None), (4, None, "y"), (5, "x" * 999, "z"), (6, "x" * 999, "z"), (7, "x" * 1000, "z"), (8, "x" * 1000, "z"), (8, "x" * 1000, "z"), (None, big, "n")]
    pages = spark.createDataFrame(rows, "page_id long, html string, digest string").withColumns({"best": F.lit(1), "id": F.lit(0)})
    where = f"file://{tmp_path}/odd-{limit}"
    manifest = warc.write_archives(pages, where)
    got = sorted(((r["id"], r["record_type"], r["refers_to"], r["payload_bytes"], r["url"]) for r in warc.read_archives(spark, where).collect()), key=str)
    want = [(1, "revisit", 2, 40_000, None), (2, "response", None, 40_000, None), (3, "response", None, 0, None), (4, "response", None, 0, None), (5, "response", None, 999, None), (6, "response", None, 999, None),
            (7, "revisit", 8, 1000, None), (8, "response", None, 1000, None), (8, "response", None, 1000, None), (None, "revisit", 2, 40_000, None)]
    assert got == sorted(want, key=str) and manifest.count() == len(rows)


def test_neighbours_in_blocks_with_other_columns(spark, sf_dir, monkeypatch):
    df = spark.read.parquet(f"{sf_dir}/embeddings.parquet")
    key = lambda x: sorted((r["query_id"], r["rank"], r["vec_id"], r["score"]) for r in x.collect())
    want = key(neighbours.nearest(df, F.col("vec_id") % 100 == 0))
    monkeypatch.setattr(neighbours, "QUERY_BLOCK", 2)
    more = df.withColumns({"id": F.lit("x"), "vector": F.lit(1), "codes": F.lit(2), "asks": F.lit(None), "score": F.lit(0.0), "rank": F.lit(9)})
    assert key(neighbours.nearest(more, F.col("vec_id") % 100 == 0)) == want
    wide = df.withColumn("embedding", F.col("embedding").cast("array<double>"))
    assert [r[:3] for r in key(neighbours.nearest(wide, F.col("vec_id") % 100 == 0))] == [r[:3] for r in want]


def test_near_classes_with_ids_of_any_type(spark):
    """Text ids, repeated ids with other texts, equal texts of other ids."""
    passage = " ".join(f"p{i}" for i in range(60))
    rows = [("b", passage), ("a", passage), ("a", "other words here"), ("a", passage), (None, passage), ("c", passage + " z"), ("d", None), ("e", "")]
    df = spark.createDataFrame(rows, "doc_id string, text string")
    got = {(r["id"], r["class_id"], r["class_size"]) for r in near_dedup.near_classes(df).collect()}
    assert got == {("b", "a", 5), ("a", "a", 5), (None, "a", 5), ("c", "a", 5), ("a", "a", 1), ("d", "d", 1), ("e", "e", 1)}
    kept = sorted(((r["doc_id"], r["text"]) for r in near_dedup.drop_near_copies(df).collect()), key=str)
    assert kept == sorted([("a", passage), ("a", "other words here"), ("d", None), ("e", "")], key=str)
