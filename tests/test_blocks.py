"""Pairs by blocks of vectors against the join of all products."""

import numpy as np
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

from channelalign.operators import binning, blocks, cluster, matching, segments, similarity
from channelalign.plans import register
from channelalign.sources.planted import planted_events
from conftest import SF, comparable
from test_plans import plan

RULES = [("intersect", {"rule": "best"}), ("intersect", {"rule": "best", "theta": 0.3}), ("union", {"rule": "best"}), ("forward", {"rule": "best"}), ("backward", {"rule": "best"}), ("intersect", {"rule": "top", "m": 3}), ("backward", {"rule": "top", "m": 2}), ("intersect", {"rule": "threshold", "theta": 0.2})]


@pytest.fixture(scope="module")
def binned(spark):
    return binning.bin_events(planted_events(spark, SF, 31)[0], binning.HOUR_US, register.ORIGIN)


@pytest.mark.parametrize("how,rule", RULES)
def test_matches_by_blocks_are_those_of_all_pairs(spark, binned, monkeypatch, how, rule):
    monkeypatch.setattr(blocks, "BLOCK", 4)
    expected = matching.reconcile(similarity.pairwise_cosine(binned, "a", "b"), how, **rule).select("u", "v", "dot", "sim")
    assert comparable(similarity.matched_cosine(binned, "a", "b", how, **rule).collect()) == comparable(expected.collect())


def test_matches_in_segments_and_several_clusters(spark, binned, monkeypatch):
    monkeypatch.setattr(blocks, "BLOCK", 4)
    weekly = segments.plan(binned, segments.segment_of_bin(binning.HOUR_US, 7))
    expected = matching.reconcile(similarity.pairwise_cosine(weekly, "a", "b", keys=("segment",)), "union", keys=("segment",))
    assert comparable(similarity.matched_cosine(weekly, "a", "b", "union", keys=("segment",)).collect()) == comparable(expected.collect())
    one = cluster.activity_bands(binned, register.BANDS)
    labels = one.unionByName(one.withColumn("cluster", F.lit(9)).where("entity % 3 = 0"))
    for rule in ({"rule": "best"}, {"rule": "top", "m": 2}):
        expected = matching.reconcile(similarity.pairwise_cosine(binned, "a", "b", labels, several=True), **rule).select("u", "v", "dot", "sim")
        assert comparable(similarity.matched_cosine(binned, "a", "b", labels=labels, several=True, **rule).collect()) == comparable(expected.collect())


@pytest.mark.parametrize("scale", [1, 3000])
@pytest.mark.parametrize("m,ties", [(1, True), (3, False)])
def test_slices_of_a_task(monkeypatch, scale, m, ties):
    """A few rows and bins at a time, with many ties; large counts are multiplied as doubles."""
    monkeypatch.setattr(blocks, "SLICE", 40)
    monkeypatch.setattr(blocks, "DENSE", 60)
    rng = np.random.default_rng(m)
    dense = [np.where(rng.random((n, 9)) < 0.4, rng.integers(1, 3, (n, 9)) * scale, 0) for n in (23, 17)]

    def side(x):
        full = [np.flatnonzero(r) for r in x]
        own = pa.RecordBatch.from_arrays([pa.array(np.arange(len(x)) * 5), pa.array((x * x).sum(axis=1)), pa.array([f - 4 for f in full], pa.list_(pa.int32())), pa.array([r[f] for r, f in zip(x, full)], pa.list_(pa.int32()))], names=["id", "sq", "bins", "cnts"])
        return blocks._Side([own.slice(0, 10), own.slice(10)])

    dot = dense[0] @ dense[1].T
    sim = dot / np.sqrt(np.maximum((dense[0] ** 2).sum(axis=1)[:, None] * (dense[1] ** 2).sum(axis=1)[None], 1))
    sim[dot == 0] = 0

    def first(s):
        rank = (s[:, None, :] > s[:, :, None]).sum(axis=2) if ties else np.argsort(np.argsort(-s, axis=1, kind="stable"), axis=1)
        return (rank < m) & (s > 0)

    u, v, d, s, f, b = (np.concatenate(c) for c in zip(*blocks._wanted(side(dense[0]), side(dense[1]), m, ties, "uv", None)))
    got = np.zeros((2, *dot.shape), bool)
    got[0, u // 5, v // 5], got[1, u // 5, v // 5] = f, b
    assert (got[0] == first(sim)).all() and (got[1] == first(sim.T).T).all()
    assert (d == dot[u // 5, v // 5]).all() and (s == sim[u // 5, v // 5]).all()
    every = list(blocks._wanted(side(dense[0]), side(dense[1]), 1, True, "", 0.5))
    assert sum(len(x[0]) for x in every) == int((sim >= 0.5).sum())


@pytest.mark.parametrize("name", ["match_best", "match_threshold", "match_top3", "forward", "backward", "metrics_final", "jaccard_found_truth", "h1_maxima", "h0_maxima", "h0_matched", "h0_pool", "h0_by_right", "cosine_all_channels"])
def test_no_product_of_all_pairs_is_shuffled(spark, name):
    text = plan(register.queries()[name](spark, SF))
    assert not any("bin" in line.split("[", 1)[1].split("]")[0] for line in text.splitlines() if "Join [" in line)


@pytest.mark.parametrize("name", ["cosine_all", "cosine_within_band", "cosine_salted", "cosine_every_channel", "jaccard_bins"])
def test_all_pairs_are_made_without_a_shuffle(spark, name):
    text = plan(register.queries()[name](spark, SF))
    assert not any("bin" in line.split("[", 1)[1].split("]")[0] for line in text.splitlines() if "Join [" in line)
    assert not any("hashpartitioning(u#" in line or "u#" in line and "v#" in line for line in text.splitlines() if "Exchange" in line)


def test_jaccard_by_blocks_is_that_of_sets(spark, binned, monkeypatch):
    monkeypatch.setattr(blocks, "BLOCK", 4)
    of = {c: {} for c in "ab"}
    for r in binned.collect():
        of[r["channel"]].setdefault(r["entity"], set()).add(r["bin"])
    want = [[u, v, len(x & y), len(x & y) / len(x | y)] for u, x in of["a"].items() for v, y in of["b"].items() if x & y]
    assert comparable(similarity.pairwise_jaccard(binned, "a", "b").collect()) == comparable(want)


def test_all_channels_by_blocks_are_those_of_the_join(spark, binned, monkeypatch):
    monkeypatch.setattr(blocks, "BLOCK", 4)
    both = similarity.all_pairs_cosine(binned).where("left = 'a' AND right = 'b'").select("u", "v", "dot", "sim")
    assert comparable(both.collect()) == comparable(similarity.pairwise_cosine(binned, "a", "b").collect())


def test_every_pair_by_blocks_is_that_of_the_join(spark, binned, monkeypatch):
    monkeypatch.setattr(blocks, "BLOCK", 4)
    key = lambda f: comparable(f.select("u", "v", "dot", "sim").collect())
    plain = key(similarity.pairwise_cosine(binned, "a", "b"))
    assert key(similarity.every_cosine(binned, "a", "b")) == key(similarity.every_cosine(binned, "a", "b", salts=3, hot=5)) == plain != []
    labels = cluster.activity_bands(binned, register.BANDS)
    assert key(similarity.every_cosine(binned, "a", "b", labels)) == key(similarity.pairwise_cosine(binned, "a", "b", labels))


def _block(rng, n, n_bins, most):
    counts = np.where(rng.random((n, n_bins)) < 0.02, rng.integers(1, most, (n, n_bins)), 0)
    counts[np.arange(n), np.arange(n)] |= 1
    full = [np.flatnonzero(r) for r in counts]
    columns = [pa.array(np.arange(n) + 7), pa.array((counts * counts).sum(axis=1)), pa.array(full, pa.list_(pa.int64())), pa.array([r[f] for r, f in zip(counts, full)], pa.list_(pa.int64()))]
    return counts, blocks._Side([pa.RecordBatch.from_arrays(columns, names=["id", "sq", "bins", "cnts"])])


@pytest.mark.parametrize("most", [3, 10_000])
def test_few_common_bins_are_not_multiplied_out(monkeypatch, most):
    """Blocks that share few bins go by an index of them: no dense side is made, and the products are the same."""
    monkeypatch.setattr(blocks, "SLICE", 200)
    monkeypatch.setattr(blocks, "BATCH", 100)
    monkeypatch.setattr(blocks, "DENSE_WORTH", 100)
    rng = np.random.default_rng(most)
    (a, x), (b, y) = _block(rng, 31, 3000, most), _block(rng, 29, 3000, most)
    monkeypatch.setattr(blocks._Side, "dense", lambda *_: pytest.fail("made a dense side"))
    slices = list(blocks._slices(x, y))
    assert [first for first, _ in slices] == list(range(0, 31, 6))
    assert (np.concatenate([d for _, d in slices]) == a @ b.T).all()


def test_pairs_leave_python_in_a_row_for_each_entity(spark, binned, monkeypatch):
    text = plan(similarity.block_cosine(binning.to_vectors(binned), "a", "b"))
    made = next(line for line in text.splitlines() if "InArrow" in line)
    assert "sims" in made and "posexplode" in text


@pytest.mark.parametrize("theta", [None, 0.3])
def test_pairs_of_several_entities_and_none(theta):
    """Entities without a pair of at least theta have no row, and each other one has its own."""
    rng = np.random.default_rng(5)
    (a, x), (b, y) = _block(rng, 40, 60, 3), _block(rng, 9, 60, 3)
    sim = (a @ b.T) / np.sqrt((a * a).sum(axis=1)[:, None] * (b * b).sum(axis=1)[None])
    a_ids = np.arange(40) + 7
    found = {(int(u), int(v)): s for us, ns, vs, _, ss in blocks._every(x, y, theta) for u, v, s in zip(np.repeat(us, ns), vs, ss)}
    want = {(int(u), j + 7): sim[k, j] for k, u in enumerate(a_ids) for j in range(9) if sim[k, j] > 0 and sim[k, j] >= (theta or 0)}
    assert found == want


def test_pairs_of_blocks_have_partitions_of_their_own(spark, binned, monkeypatch):
    monkeypatch.setattr(blocks, "BLOCK", 4)
    monkeypatch.setattr(blocks, "PART_ROWS", 1)
    a, b, on = similarity._sides(binned, "a", "b", None, ())
    dealt = blocks._dealt(blocks.pack(a, b, []), [], (1, 1))
    cells = dealt.select("i", "j").distinct().count()
    assert dealt.rdd.getNumPartitions() == blocks.PARTS * cells > 4
