import itertools
import random

import numpy as np
import pytest

from viewsize.llm import near_dup
from viewsize.llm.components import connected_components
from viewsize.llm.near_dup import drop_near_duplicates, match_threshold, near_duplicate_groups


def brute(rows, k, num, den):
    """Component of each row position, by comparing all pairs of shingle sets."""
    sets = []
    for _, text in rows:
        w = (text or "").encode().lower().split()
        sets.append(frozenset(tuple(w[i : i + k]) for i in range(len(w) - k + 1)) if len(w) >= k else frozenset([tuple(w)] if w else []))
    up = list(range(len(rows)))

    def find(x):
        while up[x] != x:
            x = up[x]
        return x

    for a, b in itertools.combinations(range(len(rows)), 2):
        A, B = sets[a], sets[b]
        if A and B:
            i = len(A & B)
            if den * i >= num * (len(A) + len(B) - i):
                up[find(a)] = find(b)
    out = {}
    for i, (doc, _) in enumerate(rows):
        out.setdefault(find(i), []).append(doc)
    return [min(out[find(i)]) for i in range(len(rows))], [len(s) for s in sets]


def check(spark, rows, k, num, den, **how):
    got = near_duplicate_groups(spark.createDataFrame(rows, "doc_id long, text string"), k=k, num=num, den=den, **how).collect()
    comp, n = brute(rows, k, num, den)
    assert sorted((r["doc_id"], r["n_shingles"], r["component_id"], r["kept"]) for r in got) == sorted((d, m, c, d == c) for (d, _), m, c in zip(rows, n, comp))


def words(rng, n, vocab=4000):
    return [f"w{rng.randrange(vocab)}" for _ in range(n)]


def test_edited_copies_against_brute_force(spark):
    """A large group of edited copies, many of them just below the threshold to any other, exact copies, a shared passage, unrelated texts."""
    rng = random.Random(4)
    base, passage = words(rng, 150), words(rng, 60)
    rows = []
    for i in range(260):
        t = list(base)
        for _ in range(rng.choice([0, 1, 2, 3, 4, 5, 6, 7])):
            at = rng.randrange(len(t))
            if rng.random() < 0.3:
                del t[at]
            else:
                t[at] = rng.choice(words(rng, 1, 30) + words(rng, 1))
        rows.append((i, " ".join(t)))
    rows += [(1000 + i, rows[7][1]) for i in range(40)]
    rows += [(2000 + i, " ".join(words(rng, 40) + passage + words(rng, 30))) for i in range(60)]
    rows += [(3000 + i, " ".join(words(rng, rng.choice([1, 2, 3, 5, 80])))) for i in range(60)]
    rng.shuffle(rows)
    check(spark, rows, 3, 85, 100)


def test_five_word_shingles(spark):
    rng = random.Random(9)
    rows = []
    for g in range(12):
        base = words(rng, 120)
        for i in range(8):
            t = list(base)
            for _ in range(rng.choice([0, 1, 2, 3])):
                t[rng.randrange(len(t))] = words(rng, 1)[0]
            rows.append((100 * g + i, " ".join(t)))
    check(spark, rows, 5, 80, 100)


def test_messy_rows(spark, messy, nothing):
    got = near_duplicate_groups(messy, k=3, num=85, den=100)
    rows = got.collect()
    assert len(rows) == messy.count()
    assert near_duplicate_groups(nothing).collect() == []
    by = {}
    for r in rows:
        by.setdefault(r["doc_id"], []).append(r)
    assert all(r["component_id"] == r["doc_id"] and r["kept"] for i in (0, 1, 2, 3, 4, 9) for r in by[i])
    assert [r["n_shingles"] for i in (0, 1, 2, 3, 4) for r in by[i]] == [0, 0, 0, 1, 1]
    assert {r["component_id"] for r in by[5] + by[6]} == {5} and [r["kept"] for r in by[6]] == [False]
    assert [r["component_id"] for r in by[8] + by[10]] == [8, 8]
    assert sorted((r["component_id"] is None, r["n_shingles"]) for r in by[None]) == [(False, 4), (True, 0)]
    left = drop_near_duplicates(messy, k=3, num=85, den=100)
    assert left.columns == messy.columns
    assert sorted((str(r["doc_id"]), r["text"] and r["text"][:9]) for r in left.collect()).count(("5", "word0 wor")) == 1


def test_threshold_and_signature():
    assert match_threshold(24, 85, 100) == 9 or 6 <= match_threshold(24, 85, 100) <= 10
    rng = np.random.default_rng(1)
    a = np.unique(rng.integers(0, 2**63, 2000, dtype=np.uint64))
    b = np.unique(np.concatenate([a[:1000], rng.integers(0, 2**63, 1000, dtype=np.uint64)]))
    same = (near_dup.signature(a, 512) == near_dup.signature(b, 512)).mean()
    assert abs(same - 1 / 3) < 0.08


def test_components(spark):
    chain = [(i, i + 1) for i in range(40)] + [(100, 7 + 100), (107, 105), (200, 200)]
    got = {r["node"]: r["root"] for r in connected_components(spark.createDataFrame(chain, "u long, v long")).collect()}
    assert got == {i: 0 for i in range(41)} | {100: 100, 105: 100, 107: 100}
    assert connected_components(spark.createDataFrame([], "u long, v long")).collect() == []


@pytest.mark.parametrize("k", [1, 5])
def test_shingles(k):
    memo = near_dup._WordHash()
    assert len(near_dup.shingles(None, k, memo)) == 0 and len(near_dup.shingles(" \n", k, memo)) == 0
    assert (near_dup.shingles("A b\tC", k, memo) == near_dup.shingles("a B  c", k, memo)).all()
    assert len(near_dup.shingles("x y z", k, memo)) == (3 if k == 1 else 1)


def test_components_without_a_common_core_against_brute_force(spark):
    """A long drifting chain, and two bridged groups of edited copies, each with strays that are near one of their texts alone: no shingle is held by most of
    such a component, and its posting lists are long."""
    rng = random.Random(21)

    def changed(t, at):
        return t[:at] + words(rng, 1, 10**6) + t[at + 1 :]

    walk = words(rng, 42 + 150, 10**6)
    texts = [walk[i : i + 42] for i in range(150)]
    texts += [changed(t, rng.randrange(8, 34)) for t in texts for _ in range(2)]
    walk = words(rng, 42 + 40, 10**6)
    texts += [walk[i : i + 42] for i in range(41)]
    for base in (walk[:42], walk[40:82]):
        for _ in range(100):
            at = rng.randrange(8, 32)
            t = changed(base, at)
            texts += [t, changed(t, at + 2)]
    rows = [(i, " ".join(t)) for i, t in enumerate(texts)]
    rng.shuffle(rows)
    check(spark, rows, 3, 85, 100)


def test_long_lists_whose_largest_component_has_no_anchor(spark):
    """The last comparison round keeps a pair in a long list although no shingle is held by most of the list's largest component."""
    sets = [(i, list(range(10 * i, 10 * i + 40))) for i in range(20)] + [(20, list(range(30, 70)) + [-1])]
    member = [(1, i, len(s), True, min(i, 1) if i < 20 else 20) for i, s in sets]
    got = near_dup._rest_pairs(spark.createDataFrame(member, "e long, cls long, n long, long boolean, comp long"), spark.createDataFrame(sets, "cls long, shingles array<long>"), 85, 100, 1)
    assert {(min(r), max(r)) for r in map(tuple, got.collect())} == {(3, 20)}


def test_few_edges_are_joined_in_one_step(spark, monkeypatch):
    from viewsize.llm import components

    steps = []
    monkeypatch.setattr(components, "settle", lambda df, name: steps.append(name) or df.localCheckpoint())
    edges = spark.createDataFrame([(i, i + 1) for i in range(40)] + [(100, 90), (None, 3), (7, 7)], "u long, v long")
    short = {r["node"]: r["root"] for r in connected_components(edges).collect()}
    assert len(steps) == 1  # rounds plan and write a table each
    monkeypatch.setattr(components, "EDGES_A_TASK", 1)
    assert short == {r["node"]: r["root"] for r in connected_components(edges.limit(8)).collect()} | short
    assert short == {i: 0 for i in range(41)} | {90: 90, 100: 90}


def test_only_a_part_of_whole_sets_is_counted(spark, monkeypatch):
    from pyspark.sql import functions as F

    from viewsize.llm import near_dup

    counted = []
    explode = F.explode
    monkeypatch.setattr(near_dup.F, "explode", lambda c: counted.append(str(c)) or explode(c))
    monkeypatch.setattr(near_dup, "settle", lambda df, name: df)
    # Whole sets of 100: two that share 95 elements, one that shares 40 with either.
    sets = {1: range(0, 100), 2: range(5, 105), 3: [*range(20, 60), *range(500, 560)]}
    own = spark.createDataFrame([(-1, c, c, 100, [h * 7_919_317 for h in d]) for c, d in sets.items()], "grp long, cls long, comp long, n long, d array<long>")
    pairs = near_dup._met(own, 85, 100, 1, False).collect()
    assert {tuple(sorted(r)) for r in pairs} == {(1, 2)}
    assert not any("'d'" in c or "<d>" in c or "explode(d)" in c for c in counted) and any("early" in c for c in counted)


LISTS = "e long, cls long, comp long, n long, top long, most long"


def test_members_that_a_kernel_does_not_fit_are_described_once(spark):
    """Strays that hold half of a kernel differ from it in nine tenths of their size: their whole sets are needed anyway, their differences only repeat them."""
    kernel = list(range(40))
    sets = {i: kernel for i in range(10)} | {100 + i: kernel[:22] + list(range(1000 * i + 100, 1000 * i + 118)) for i in range(20)}
    sets[200] = sets[105][:-1] + [-5]
    lists = [(1, c, c if c >= 100 else 0, 40, 0, 10) for c in sets]
    made = near_dup._differences(spark.createDataFrame(lists, LISTS), spark.createDataFrame([*sets.items()], "cls long, shingles array<long>"), 85, 100)
    rows = [(r["grp"], r["cls"], len(r["d"])) for r in made.collect()]
    assert sorted(r[:2] for r in rows) == sorted([(0, c) for c in range(10)] + [(-1, c) for c in sets if c >= 100])
    assert sum(r[2] for r in rows) == 21 * 40  # the members of the component are the kernel; nine tenths more before
    pairs = near_dup._distant_pairs(spark.createDataFrame(lists, LISTS), spark.createDataFrame([*sets.items()], "cls long, shingles array<long>"), 85, 100, 1)
    assert (105, 200) in {tuple(sorted(r)) for r in map(tuple, pairs.collect())}


@pytest.mark.parametrize("cuts", [(10,), (8,), (4,), (1,), (10, 8, 6, 4)])
def test_any_cut_of_a_group_leaves_all_links(spark, monkeypatch, cuts):
    """Pairs of strays at the threshold, at all distances from the kernel: what the candidates link is what all pairs link."""
    monkeypatch.setattr(near_dup, "CUTS", cuts)
    rng = random.Random(11)
    value = lambda: rng.randrange(-(2**62), 2**62)
    kernel = [value() for _ in range(120)]
    sets = {i: kernel for i in range(6)}
    for i in range(70):
        cut = rng.randrange(0, 100)
        a = kernel[cut:] + [value() for _ in range(rng.choice([cut, cut // 2, cut + 20]))]
        rng.shuffle(a)
        gone = rng.randrange(0, len(a) // 12 + 1)
        allowed = (15 * len(a) - 100 * gone) // 85  # at most so many more, for 85 of 100
        b = a[gone:] + [value() for _ in range(rng.choice([max(0, allowed), max(0, allowed) + 1, max(0, allowed // 2)]))]
        sets |= {100 + 2 * i: a, 101 + 2 * i: b}
    comp = {c: c if c >= 100 else 0 for c in sets}
    lists = spark.createDataFrame([(1, c, comp[c], len(sets[c]), 0, 6) for c in sets], LISTS)
    pairs = near_dup._distant_pairs(lists, spark.createDataFrame([*sets.items()], "cls long, shingles array<long>"), 85, 100, 1).collect()
    own = {c: frozenset(s) for c, s in sets.items()}
    linked = lambda a, b: 100 * len(own[a] & own[b]) >= 85 * len(own[a] | own[b])

    def parts(edges):
        up = dict(comp)
        for a, b in edges:
            x, y = up[a], up[b]
            up = {c: min(x, y) if r in (x, y) else r for c, r in up.items()} if x != y else up
        return up

    everything = parts(p for p in itertools.combinations(sets, 2) if linked(*p))
    assert len(set(everything.values())) < len(sets) - 40
    assert parts(p for p in map(tuple, pairs) if linked(*p)) == everything


def test_whole_sets_post_no_more_than_a_link_may_leave_out(spark, monkeypatch):
    """Of 100 elements, 15 at most are not in a linked set, so 16 are posted."""
    posted = []
    monkeypatch.setattr(near_dup, "settle", lambda df, name: posted.append(df) or df)
    sets = {1: range(100), 2: range(100)}
    own = spark.createDataFrame([(-1, c, c, 100, [h * 7_919_317 for h in d]) for c, d in sets.items()], "grp long, cls long, comp long, n long, d array<long>")
    assert {tuple(sorted(r)) for r in near_dup._met(own, 85, 100, 1, False).collect()} == {(1, 2)}
    assert posted[0].count() == 2 * 16


def test_exploded_tables_are_not_broadcast(spark, tmp_path):
    """400,000 postings or elements come from files far below the limit of a broadcast, 10 MB."""
    from pyspark.sql import functions as F

    from viewsize.llm import near_dup

    def plan(df):
        return df._jdf.queryExecution().executedPlan().toString()

    (spark.range(2000).select(F.col("id").alias("cls"), F.lit(9).cast("long").alias("n"), F.transform(F.sequence(F.lit(1), F.lit(200)), lambda i: i).alias("sig"))).write.parquet(str(tmp_path / "classes"))
    seen = []
    with pytest.MonkeyPatch.context() as m:
        m.setattr(near_dup, "settle", lambda df, name: seen.append(plan(df)) or df)
        classes = spark.read.parquet(str(tmp_path / "classes"))
        seen.append(plan(near_dup._postings(classes, 8)))
        pairs = spark.createDataFrame([(1, 2)], "a long, b long")
        near_dup._confirmed(pairs, classes, classes.select("cls", F.col("sig").cast("array<long>").alias("shingles")), 8, 85, 100, 1)
        own = classes.select(F.lit(-1).cast("long").alias("grp"), "cls", F.col("cls").alias("comp"), "n", F.col("sig").cast("array<long>").alias("d"))
        own.write.parquet(str(tmp_path / "own"))
        near_dup._met(spark.read.parquet(str(tmp_path / "own")), 85, 100, 1, False)
    assert len(seen) == 4 and not any("explode" in part.split("\n\n")[0] for p in seen for part in p.split("BroadcastExchange")[1:])
    assert not any("BroadcastHashJoin" in p for p in seen)


def test_bitmaps_leave_every_link_and_little_else(spark, monkeypatch):
    """What is posted beside an element is a bitmap, far shorter than the difference; its bound never exceeds the true difference, for widths of any two sizes that may be linked."""
    from pyspark.sql import functions as F

    from viewsize.llm import near_dup

    rng = random.Random(5)
    value = lambda: rng.randrange(-(2**63), 2**63)
    rows = []
    for i in range(60):
        a = [value() for _ in range(rng.choice([1, 2, 31, 32, 33, 60, 64, 65, 500]))]
        b = a[rng.randrange(0, len(a) // 8 + 1) :] + [value() for _ in range(rng.randrange(0, len(a) // 9 + 1))]
        b = b if i % 3 else [value() for _ in b]
        rows.append((a, b, *(near_dup.bitmap(np.array(x, np.int64), near_dup.bitmap_words(len(x))).tolist() for x in (a, b))))
    df = spark.createDataFrame(rows, "a array<long>, b array<long>, c array<long>, d array<long>")
    got = df.select("a", "b", near_dup._least_difference(F.col("c"), F.col("d"), 80, 100).alias("least")).collect()
    true = lambda r: len(set(r["a"]) ^ set(r["b"]))
    assert all(r["least"] <= true(r) for r in got) and sum(r["least"] for r in got) > 0.5 * sum(map(true, got))
    posted = []
    monkeypatch.setattr(near_dup, "settle", lambda df, name: posted.append(df) or df)
    sets = {1: [value() for _ in range(400)], 3: [value() for _ in range(400)]} | {}
    sets[2], sets[4] = sets[1][20:] + [value() for _ in range(20)], sets[3][200:] + sets[1][:200]
    own = spark.createDataFrame([(0, c, c, 400, d) for c, d in sets.items()], "grp long, cls long, comp long, n long, d array<long>")
    assert {tuple(sorted(r)) for r in near_dup._met(own, 85, 100, 1, True).collect()} == {(1, 2)}
    assert posted[0].agg(F.max(F.size("d"))).first()[0] == 16  # 400 before
