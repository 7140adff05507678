"""Sharding, mixing, packing."""

import math
import zlib
from collections import Counter, defaultdict

import numpy as np
import pytest
from pyspark.sql import functions as F

from viewsize.llm import mixing, packing, sharding

SF = "/root/testdata/sf0.01"


def check_shards(rows, shards):
    slots = defaultdict(list)
    for r in rows:
        slots[r["shard"]].append(r["slot"])
    assert set(slots) <= set(range(shards))
    assert all(sorted(s) == list(range(len(s))) for s in slots.values())


def test_shards_are_balanced_and_keep_groups(spark):
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    rows = sharding.shard_documents(docs, 40).collect()
    texts = {r["doc_id"]: r["text"] for r in docs.collect()}
    check_shards(rows, 40)
    weight = Counter()
    for r in rows:
        raw = texts[r["doc_id"]].encode()
        assert (r["size"], r["text_crc32"], r["law"], r["grown_shard"]) == (len(raw) + 16, zlib.crc32(raw), "bytes", None)
        weight[r["shard"]] += r["size"]
    mean = sum(weight.values()) / 40
    assert len(weight) == 40 and max(weight.values()) < 1.06 * mean and min(weight.values()) > 0.94 * mean
    of = defaultdict(set)
    for r in rows:
        of[texts[r["doc_id"]]].add(r["shard"])
    sizes = Counter(texts.values())
    assert all(len(s) == 1 for t, s in of.items() if sizes[t] * (len(t.encode()) + 16) < mean / 4)


def test_a_hot_group_is_split(spark):
    rows = sharding.shard_documents(spark.range(4000).selectExpr("id AS doc_id", "CASE WHEN id % 3 = 0 THEN 'same text here' ELSE concat('t', id) END AS text"), 10).collect()
    check_shards(rows, 10)
    n = Counter(r["shard"] for r in rows)
    assert max(n.values()) < 1.1 * 400


def test_place_prefers_the_highest_dot_product():
    assert sharding.place(np.array([[0.5, 0.1], [0.3, 0.1], [0.2, 0.8]]), 2).tolist() == [1, 0, 0]


def test_dealing_at_once_equals_one_by_one():
    rng = np.random.default_rng(0)
    for _ in range(200):
        scores, step, n = rng.normal(size=rng.integers(2, 9)) * 10, rng.random() + 0.01, int(rng.integers(0, 200))
        naive = np.zeros(len(scores), int)
        for _ in range(n):
            naive[int((scores - step * naive).argmax())] += 1
        assert (sharding.deal(scores, step, n) == naive).all()


def test_twenty_thousand_groups_are_placed_by_the_rule(spark):
    """Every class of groups against a plain loop that places one group after the other where the dot product with what is left is highest."""
    docs = spark.range(20_000).selectExpr("id AS doc_id", "concat('t', id, ' ', repeat('word ', CAST(pow(2, (id * 37 % 100) / 16) AS INT)))  AS text")
    rows = sharding.shard_documents(docs, 10, parcels=256).collect()
    check_shards(rows, 10)
    total = np.array([sum(r["size"] for r in rows), sum(r["tokens"] for r in rows), len(rows)], float)
    classes = defaultdict(list)
    for r in rows:
        v = (r["size"], r["tokens"], 1)
        classes[tuple(int(np.floor(4 * np.log2(x + 1))) for x in v)].append((v, r["shard"]))
    items = {c: np.mean([v for v, _ in own], axis=0) / total * sharding.WEIGHTS for c, own in classes.items()}
    left = np.tile(sharding.WEIGHTS / 10, (10, 1))
    order = sorted(sorted(classes), key=lambda c: -items[c].max())
    for c in order:
        naive = Counter()
        for _ in classes[c]:
            at = int((left @ items[c]).argmax())
            naive[at] += 1
            left[at] -= items[c]
        assert Counter(s for _, s in classes[c]) == naive
    weight = Counter()
    for r in rows:
        weight[r["shard"]] += r["size"]
    assert max(weight.values()) < 1.02 * total[0] / 10 and min(weight.values()) > 0.98 * total[0] / 10


def test_draws_without_replacement_of_any_size(monkeypatch):
    rng = np.random.default_rng(1)
    numpys = rng.hypergeometric(400_000, 900_000, 300_000, 4000)
    monkeypatch.setattr(mixing, "_NUMPY_MOST", 0)
    own = np.array([mixing.hypergeometric(400_000, 900_000, 300_000, rng) for _ in range(4000)])
    assert abs(own.mean() - numpys.mean()) < 20 and abs(own.std() / numpys.std() - 1) < 0.06
    small = np.bincount([mixing.hypergeometric(5, 7, 4, rng) for _ in range(8000)], minlength=5) / 8000
    exact = np.array([math.comb(5, x) * math.comb(7, 4 - x) / math.comb(12, 4) for x in range(5)])
    assert abs(small - exact).max() < 0.03
    big = np.array([mixing.hypergeometric(3 * 10**15, 5 * 10**15, 10**15, rng) for _ in range(1000)])
    assert abs(big.mean() / (3 / 8 * 10**15) - 1) < 1e-7 and 0.9 < big.std() / math.sqrt(10**15 * 3 / 8 * 5 / 8 * 7 / 8) < 1.1


def test_two_billion_slots_are_drawn_not_rounded():
    quota, slots = np.array([1_500_000_000, 400_000_000, 100_000_007]), 500_000_000
    got = [mixing.shard_counts(quota, i, 5, slots, 3) for i in range(5)]
    assert (sum(c for _, c in got) == quota).all() and all((a[0] + a[1] == b[0]).all() for a, b in zip(got, got[1:]))
    expected = quota / quota.sum() * slots
    off = np.array([c - expected for _, c in got[:4]])
    assert (np.abs(off) > 0.6).any() and (np.abs(off) < 10 * np.sqrt(expected)).all()  # a draw scatters, a rounded expectation doesn't


def test_mixture_against_a_plain_loop(spark):
    """Each document's taken words: the streams laid out in plain lists, every slot's words counted one by one."""
    docs = spark.read.parquet(f"{SF}/documents.parquet").where("doc_id % 9 = 0")
    numbered = mixing._numbered(docs, "sizes").cache()
    _, _, plan = mixing.mix_rows(numbered, 16, seed=17)
    streams = defaultdict(list)
    for r in numbered.withColumn("k", F.xxhash64(F.lit(17), "doc_id", "text_key")).orderBy("k", "n").collect():
        streams[r["source"]] += [r["doc_id"]] * r["size"]
    taken = Counter()
    for i, name in enumerate(plan.names):
        for slot in range(plan.slots[i]):
            _, number, take = plan.blocks(i, np.array([slot]))
            taken.update(streams[name][int(number[0]) * 16 : int(number[0]) * 16 + int(take[0])])
    assert {r["doc_id"]: r["taken"] for r in mixing.mixture_report(docs, 16).collect() if r["taken"]} == dict(taken)


def test_targets():
    assert mixing.targets([100, 100, 100], [1, 2, 3]) == pytest.approx([50, 100, 150])
    got = mixing.targets([10, 1000, 1000], [3, 1, 1])
    assert got == pytest.approx([30, 990, 990])
    got = mixing.targets([0, 5, 20], [1, 1, 1])
    assert got[0] == 0 and sum(got) == pytest.approx(25) and all(t <= 3 * s for t, s in zip(got, [0, 5, 20]))
    assert mixing.targets([], []) == []


@pytest.mark.parametrize("n", [1, 2, 3, 17, 1000, 4097])
def test_permutation(n):
    for key in (0, 5):
        assert sorted(mixing.permute(np.arange(n), n, key).tolist()) == list(range(n))
    assert n < 10 or mixing.permute(np.arange(n), n, 1).tolist() != mixing.permute(np.arange(n), n, 2).tolist()


def test_shard_counts_add_up():
    quota = np.array([5000, 17, 0, 12_345])
    n = -(-quota.sum() // 4096)
    got = [mixing.shard_counts(quota, i, n, 4096, 3) for i in range(n)]
    assert (sum(c for _, c in got) == quota).all()
    assert (got[0][0] == 0).all() and all((got[i][0] + got[i][1] == got[i + 1][0]).all() for i in range(n - 1))
    assert all(c.sum() == 4096 for _, c in got[:-1])


def test_mixture(spark):
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    for block in (7, 512):
        rows = mixing.mixture_report(docs, block).collect()
        taken, target, size = Counter(), {}, Counter()
        for r in rows:
            assert 0 <= r["taken"] <= 3 * r["size"]
            taken[r["source"]] += r["taken"]
            size[r["source"]] += r["size"]
            target[r["source"]] = r["target"]
        assert all(abs(taken[s] - target[s]) <= 1 for s in target) and sum(target.values()) == pytest.approx(sum(size.values()))
        again = mixing.mixture_report(docs.repartition(5), block).collect()
        assert sorted((r["doc_id"], r["taken"]) for r in rows) == sorted((r["doc_id"], r["taken"]) for r in again)


def test_mixed_documents_hold_what_is_taken(spark):
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    report = {r["doc_id"]: r["taken"] for r in mixing.mixture_report(docs, 64).collect()}
    got = Counter()
    texts = {r["doc_id"]: r["text"] for r in docs.collect()}
    for r in mixing.mix_documents(docs, 64).collect():
        got[r["doc_id"]] += len(r["text"].encode().split())
        assert r["n_chars"] == len(r["text"])
        assert all(line in texts[r["doc_id"]] for line in r["text"].split("\n"))
    assert got == Counter({d: t for d, t in report.items() if t})


def check_packed(rows, sizes, capacities):
    bins, pieces = defaultdict(list), defaultdict(list)
    for r in rows:
        pieces[r["doc_id"]].append((r["first_word"], r["n_words"]))
        if r["n_words"]:
            bins[r["bin"]].append(r)
        else:
            assert r["bin"] is None and r["capacity"] is None
    for own in bins.values():
        own.sort(key=lambda r: r["bin_offset"])
        at = 0
        for r in own:
            assert r["bin_offset"] == at
            at += r["n_words"]
        assert {r["bin_words"] for r in own} == {at} and {r["capacity"] for r in own} == {min(c for c in capacities if c >= at)}
    for doc, n in sizes.items():
        own = sorted(pieces[doc])
        assert sum(w for _, w in own) == n and all(a == sum(w for _, w in own[:i]) for i, (a, _) in enumerate(own))
    return bins


def test_packing(spark):
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    sizes = {r["doc_id"]: len(r["text"].encode().split()) for r in docs.collect()}
    bins = check_packed(packing.pack_documents(docs).collect(), sizes, packing.CAPACITIES)
    fill = sum(sizes.values()) / sum(b[0]["capacity"] for b in bins.values())
    assert fill > 0.97 and len({b[0]["capacity"] for b in bins.values()}) > 1


def naive_best_fit(sizes, capacity):
    bins = []
    for s in sorted(sizes, reverse=True):
        fits = [b for b in bins if capacity - b[0] >= s]
        if fits:
            max(fits, key=lambda b: b[0])[0] += s
        else:
            bins.append([s])
    return sorted(b[0] for b in bins)


def test_histogram_packing_equals_best_fit_decreasing():
    rng = np.random.default_rng(2)
    for top in (20, 100):
        sizes = rng.integers(1, top + 1, 300).tolist()
        _, bins, _ = packing.pack_histogram(Counter(sizes), (top,))
        assert sorted(u for lo, hi, u, _ in bins for _ in range(lo, hi)) == naive_best_fit(sizes, top)


def naive_variable_fit(counts, allowed, costs):
    """Bins as plain lists: each item into the open bin with the least room that takes it; none: bins of the capacity of least cost for what is left of its size."""
    bins, smaller = [], sum(s * n for s, n in counts.items())
    for size in sorted(counts, reverse=True):
        left = counts[size]
        smaller -= size * left
        while left:
            fits = [b for b in bins if b[0] - b[1] >= size]
            if fits:
                min(fits, key=lambda b: b[0] - b[1])[1] += size
                left -= 1
                continue
            c = packing._opening(size, left, smaller, {c: costs[c] for c in allowed})
            each = min(left, c // size)
            bins += [[c, each * size] for _ in range(left // each)]
            left -= left // each * each
    return sorted((u, min(c for c in costs if c >= u)) for _, u in bins)


def test_several_capacities_against_plain_bins():
    """The choice among capacities, their prefixes, and the downsizing of each bin to its contents."""
    rng = np.random.default_rng(4)
    for capacities in ((8, 16, 32), (10, 100), (5, 7, 50, 64)):
        for _ in range(4):
            counts = Counter(rng.integers(1, capacities[-1] + 1, 120).tolist())
            costs = {c: packing.cost(c) for c in capacities}
            tried = [naive_variable_fit(counts, capacities[:i], costs) for i in range(1, len(capacities) + 1) if capacities[i - 1] >= max(counts)]
            best = min(tried, key=lambda bins: sum(costs[c] for _, c in bins))
            _, bins, price = packing.pack_histogram(counts, capacities)
            assert price == pytest.approx(sum(costs[c] for _, c in best))
            assert sorted((u, c) for lo, hi, u, c in bins for _ in range(lo, hi)) == best


def test_messy_rows(spark, messy, nothing):
    n = messy.count()
    rows = sharding.shard_documents(messy, 4).collect()
    assert len(rows) == n
    check_shards(rows, 4)
    assert {r["text_crc32"] for r in rows if r["doc_id"] in (0, 1)} == {0} and {r["size"] for r in rows if r["doc_id"] in (0, 1)} == {16}
    rows = mixing.mixture_report(messy, 64).collect()
    assert len(rows) == n and all(r["taken"] <= 3 * r["size"] for r in rows)
    by = defaultdict(lambda: [0, 0.0])
    for r in rows:
        by[r["source"]] = [by[r["source"]][0] + r["taken"], r["target"]]
    assert all(abs(t - g) <= 1 for t, g in by.values()) and None in by
    rows = packing.pack_documents(messy).collect()
    assert {r["doc_id"] for r in rows} == {r["doc_id"] for r in messy.collect()}
    assert sum(r["n_words"] for r in rows if r["doc_id"] == 6) == 60_000
    for f in (sharding.shard_documents, mixing.mixture_report, mixing.mix_documents, packing.pack_documents):
        assert f(nothing).collect() == []
