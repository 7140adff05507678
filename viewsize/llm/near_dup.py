"""Near-duplicate groups by an inverted join on MinHash signature coordinates.

A text becomes the set of its word shingles, the set a signature of ``coords`` minima. Equal sets are one class from the
start, so exact copies never meet each other. Each class is posted under its (coordinate, value) pairs. Two classes that
agree on ``match`` of ``coords`` coordinates must share one of the ``coords - match + 1`` rarest pairs of either, so

* prefix: pairs that occur once are dropped, a class with fewer than ``match`` pairs left is dropped, and of the m left
  only the m - match + 1 rarest are posted;
* skip: the frequent pairs are never merged; the full number of collisions is read off the two signatures.

Within a posting list pairs are not enumerated. A round compares all members with one pivot of their list; members already
in one component need no further comparison. After the rounds, members of short lists are compared with those of other components
there. Members of long lists are described by their differences from a kernel, the shingles that most of the list's largest
component have, and meet where they share one of the rarer elements of these differences, as a prefix filter on full sets has it.
This is exact for any list, and the strays of a large group of edited copies meet no more of it than may be linked with them.
Pairs at or above ``match`` collisions are confirmed on the full shingle sets.

``match`` follows from the threshold: the largest value that a pair exactly at the threshold misses with a chance below
``miss`` (default 1e-8).
"""

from __future__ import annotations

from math import comb

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..session import ship
from .common import settle
from .components import connected_components

# Odd 64-bit multipliers of the shingle hash.
_STEP, _MIX = 0x9E3779B97F4A7C15, 0xBF58476D1CE4E5B9
_MEMO_WORDS = 300_000
#: At most so many document ids (8 bytes each) are broadcast; more are joined by shuffling.
BROADCAST_IDS = 500_000
#: Postings to a task in the steps over posting lists.
POSTINGS_A_TASK = 20_000
#: Lists with more members than this are long.
LONG = 16
#: About so many members of a component are asked for its kernel.
KERNEL_MEMBERS = 64
#: Members of a group that one task compares with the kernel.
MEMBERS_A_CHUNK = 1000
#: So many times the elements that a difference has to post are counted, to post the rarer ones.
EARLY = 1.8
#: Tenths of its own size that a member may differ from its group's kernel by; each group takes the one that leaves the fewest elements to describe.
CUTS = (10, 8, 6, 4)


class _WordHash(dict):
    def __missing__(self, word: bytes) -> int:
        if len(self) > _MEMO_WORDS:
            self.clear()
        value = self[word] = xxhash.xxh3_64_intdigest(word)
        return value


def shingles(text: str | None, k: int, memo: dict) -> np.ndarray:
    """Distinct 64-bit hashes, sorted, of the k-word shingles of a text (A-Z lower-cased); fewer words: one of the whole sequence."""
    found = (text or "").encode("utf-8", "surrogatepass").lower().split()
    if not found:
        return np.empty(0, np.uint64)
    if len(found) < k:
        return np.array([xxhash.xxh3_64_intdigest(b" ".join(found), seed=k)], np.uint64)
    h = np.fromiter(map(memo.__getitem__, found), np.uint64, len(found))
    acc = h[: len(h) - k + 1].copy()
    for i in range(1, k):
        acc *= np.uint64(_STEP)
        acc ^= acc >> np.uint64(29)
        acc += h[i : len(h) - k + 1 + i]
    acc ^= acc >> np.uint64(32)
    acc *= np.uint64(_MIX)
    acc ^= acc >> np.uint64(29)
    return np.unique(acc)


def _multipliers(coords: int) -> tuple[np.ndarray, np.ndarray]:
    rng = np.random.default_rng(20_011)
    return rng.integers(1, 2**63, coords, dtype=np.uint64) * np.uint64(2) + np.uint64(1), rng.integers(0, 2**63, coords, dtype=np.uint64)


def signature(hashes: np.ndarray, coords: int, _kept: dict = {}) -> np.ndarray:
    """Minima of ``coords`` multiply-shift permutations, as int32."""
    mult, flip = _kept.setdefault(coords, _multipliers(coords))
    low = np.full(coords, 0xFFFFFFFFFFFFFFFF, np.uint64)
    for at in range(0, len(hashes), 512):  # a block that stays in the cache
        x = hashes[at : at + 512] ^ flip[:, None]
        x *= mult[:, None]
        low = np.minimum(low, x.min(axis=1))
    return (low >> np.uint64(32)).astype(np.uint32).view(np.int32)


def match_threshold(coords: int, num: int, den: int, miss: float = 1e-8) -> int:
    """The largest number of collisions that a pair of similarity num/den stays under with a chance below ``miss``."""
    s, below = num / den, 0.0
    for t in range(coords + 1):
        below += comb(coords, t) * s**t * (1 - s) ** (coords - t)
        if below > miss:
            return max(1, t)
    return coords


def _signer(k: int, coords: int):
    def run(batches):
        memo = _WordHash()
        for batch in batches:
            n, prints, sigs = [], [], []
            for text in batch.column(2):
                h = shingles(text.as_py(), k, memo)
                n.append(len(h))
                prints.append(xxhash.xxh3_128_digest(h.tobytes()) if len(h) else None)
                sigs.append(signature(h, coords) if len(h) else None)
            yield pa.RecordBatch.from_arrays(
                [batch.column(0), batch.column(1), pa.array(n, pa.int64()), pa.array(prints, pa.binary()), pa.array(sigs, pa.list_(pa.int32()))],
                names=["doc_id", "text_key", "n", "print", "sig"],
            )

    return run


def _setter(k: int):
    def run(batches):
        memo = _WordHash()
        for batch in batches:
            for at in range(0, batch.num_rows, 500):
                part = batch.slice(at, 500)
                sets = [shingles(t.as_py(), k, memo) for t in part.column(0)]
                yield pa.RecordBatch.from_arrays(
                    [pa.array([xxhash.xxh3_128_digest(x.tobytes()) for x in sets], pa.binary()), pa.array([x.view(np.int64) for x in sets], pa.list_(pa.int64()))],
                    names=["print", "shingles"],
                )

    return run


def bitmap(elements: np.ndarray, words: int) -> np.ndarray:
    """A bit for each element, by a hash of it, in ``words`` (a power of two) whole numbers of 64 bits. The bitmap of half as many words is the halves of this one or-ed."""
    h = elements.view(np.uint64) * np.uint64(_MIX)
    h ^= h >> np.uint64(32)
    at = h & np.uint64(64 * words - 1)
    out = np.zeros(words, np.uint64)
    np.bitwise_or.at(out, (at >> np.uint64(6)).astype(np.int64), np.uint64(1) << (at & np.uint64(63)))
    return out.view(np.int64)


def bitmap_words(n: int) -> int:
    """Words of the bitmaps of members of size n: two to four bits for each element of the set."""
    return 1 << max(0, -(-n // 32) - 1).bit_length()


def _marker(batches):
    """The last column, lists of elements, as bitmaps whose width follows from the column n."""
    for batch in batches:
        for at in range(0, batch.num_rows, 500):
            part = batch.slice(at, 500)
            sets = [np.asarray(x.values.to_numpy(zero_copy_only=False), np.int64) for x in part.column(part.num_columns - 1)]
            marks = [bitmap(x, bitmap_words(n)) for x, n in zip(sets, part.column("n").to_pylist())]
            yield pa.RecordBatch.from_arrays([*part.columns[:-1], pa.array(marks, pa.list_(pa.int64()))], names=part.schema.names)


def _least_difference(a, b, num: int, den: int):
    """At least so many elements are in one only of two sets of such bitmaps: the bits that are. The wider bitmap is folded to the other's width; sizes that allow the threshold
    are few doublings apart (others: null)."""

    def fold(x, other):
        half = (F.size(x) / 2).cast("int")
        return F.when(F.size(x) > F.size(other), F.zip_with(F.slice(x, F.lit(1), half), F.slice(x, half + 1, half), lambda p, q: p.bitwiseOR(q))).otherwise(x)

    for _ in range((-(-den // num) - 1).bit_length()):
        a, b = fold(a, b), fold(b, a)
    return F.aggregate(F.zip_with(a, b, lambda p, q: F.bit_count(p.bitwiseXOR(q))), F.lit(0), lambda s, x: s + x)


def sign(docs: DataFrame, k: int = 5, coords: int = 24) -> DataFrame:
    """(doc_id, text_key, n, print, sig) of every row: hash of the text, shingle count, digest of the set (null if it is empty), signature."""
    ship(docs.sparkSession)
    text = F.col("text").cast("string")
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.xxhash64(text).alias("text_key"), text.alias("text"))
    return rows.mapInArrow(_signer(k, coords), "doc_id long, text_key long, n long, print binary, sig array<int>")


def _postings(classes: DataFrame, match: int) -> DataFrame:
    """(e, cls, n, long) of the rarest pairs of each class that matter and that two classes post at least; e is a (coordinate, value) pair as one long.

    Spark sizes an exploded table, and arrays that it reads, as if each array had one element, so it would broadcast millions of postings or signatures through
    the driver; joins of such tables, here and below, are merged."""
    pair = F.shiftleft(F.col("at").cast("long"), 32).bitwiseOR(F.col("value").cast("long").bitwiseAND(F.lit(0xFFFFFFFF)))
    posted = classes.select("cls", "n", F.posexplode("sig").alias("at", "value")).select("cls", "n", pair.alias("e"))
    often = posted.groupBy("e").agg(F.count("*").alias("freq")).where("freq > 1")
    own = posted.hint("merge").join(often, "e").groupBy("cls", "n").agg(F.array_sort(F.collect_list(F.struct("freq", "e"))).alias("own"))  # at most coords a class
    prefix = own.where(F.size("own") >= match).select("cls", "n", F.explode(F.slice("own", F.lit(1), F.size("own") - match + 1)).alias("x"))
    prefix = settle(prefix.select(F.col("x.e").alias("e"), "cls", "n"), "prefix")
    lengths = prefix.groupBy("e").agg(F.count("*").alias("members")).where("members > 1")
    return prefix.hint("merge").join(lengths, "e").select("e", "cls", "n", (F.col("members") > LONG).alias("long"))


def _sets(docs: DataFrame, wanted: DataFrame, k: int) -> DataFrame:
    """(cls, shingles) of the wanted classes (cls, print, doc_id), from one document of each."""
    some = F.coalesce(F.col("doc_id").cast("long"), F.lit(-1)).alias("some_id")
    ids = wanted.select(some).distinct()
    ids = F.broadcast(ids) if wanted.count() <= BROADCAST_IDS else ids
    texts = docs.select(some, F.col("text").cast("string").alias("text")).join(ids, "some_id").select("text")
    found = texts.mapInArrow(_setter(k), "print binary, shingles array<long>")
    return found.join(wanted.select("cls", "print"), "print").select("cls", "shingles").dropDuplicates(["cls"])


def _confirmed(pairs: DataFrame, classes: DataFrame, sets: DataFrame, match: int, num: int, den: int, tasks: int) -> DataFrame:
    """(u, v) of those pairs (a, b) whose sizes allow the threshold, whose signatures collide often enough and whose full sets reach it."""
    pairs = pairs.select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).distinct().coalesce(tasks)
    sig = classes.select("cls", "n", "sig")
    met = pairs.join(sig.toDF("a", "na", "sa").hint("merge"), "a").join(sig.toDF("b", "nb", "sb").hint("merge"), "b").where(F.lit(den) * F.least("na", "nb") >= F.lit(num) * F.greatest("na", "nb"))
    same = F.aggregate(F.zip_with("sa", "sb", lambda x, y: (x == y).cast("int")), F.lit(0), lambda s, x: s + x)
    likely = settle(met.where(same >= match).select("a", "b").coalesce(tasks), "likely")
    both = likely.join(sets.toDF("a", "sa"), "a").join(sets.toDF("b", "sb"), "b")
    met = both.select("a", "b", F.size(F.array_intersect("sa", "sb")).alias("inter"), (F.size("sa") + F.size("sb")).alias("total"))
    return met.where(F.lit(den) * F.col("inter") >= F.lit(num) * (F.col("total") - F.col("inter"))).select(F.col("a").alias("u"), F.col("b").alias("v")).coalesce(tasks)


def _star_pairs(member: DataFrame, turn: int) -> DataFrame:
    """(a, b): each list's pivot, another in each turn, with its members of other components."""
    mask = F.lit(int(np.random.default_rng(turn).integers(0, 2**62)))
    lead = member.groupBy("e").agg(F.min("comp").alias("lo"), F.max("comp").alias("hi"), F.min(F.col("cls").bitwiseXOR(mask)).alias("p")).where("lo < hi")
    pivot = lead.select("e", F.col("p").bitwiseXOR(mask).alias("a"))
    if not turn:
        return member.join(pivot, "e").where("cls <> a").select("a", F.col("cls").alias("b"))
    own = member.join(pivot, "e").where("cls = a").select("e", "a", F.col("comp").alias("comp_a"))
    return member.join(own, "e").where("comp <> comp_a").select("a", F.col("cls").alias("b"))


def _differences(lists: DataFrame, sets: DataFrame, num: int, den: int) -> DataFrame:
    """lists (e, cls, comp, n, top, most) -> (grp, cls, comp, n, d): the members described by what sets them apart from a kernel, d = set xor kernel.

    A list whose largest component ``top`` has several members is of group ``top``; the kernel is the set of shingles that most of some 64 members of that
    component have. Any set would do as a kernel, so drawing those members costs no link. All other lists are of group -1, whose kernel is empty.
    A member that differs from its kernel in more than a part of its size, the cut, goes to group -1, and so does one from which such a member is in reach.
    Both are right for any cut. A kernel that fits badly describes its members at length who are in group -1 as well, so each group takes its own cut."""
    who = lists.select(F.when(F.col("most") > 1, F.col("top")).otherwise(F.lit(-1)).alias("grp"), "cls", "comp", "n").distinct()
    who = settle(who, "who")
    near = who.where("grp >= 0")
    held = near.groupBy("grp").agg(F.count_if(F.col("comp") == F.col("grp")).alias("size"), F.ceil(F.count("*") / MEMBERS_A_CHUNK).cast("int").alias("chunks"))
    some = near.where("comp = grp").join(held, "grp").where(F.pmod(F.xxhash64("cls"), F.greatest(F.lit(1), F.floor(F.col("size") / KERNEL_MEMBERS))) == 0).select("grp", "cls")
    drawn = some.groupBy("grp").agg(F.count("*").alias("drawn"))
    common = some.join(sets, "cls").select("grp", F.explode("shingles").alias("h")).groupBy("grp", "h").agg(F.count("*").alias("c")).join(drawn, "grp").where("2 * c > drawn")
    kernels = held.join(common.groupBy("grp").agg(F.collect_list("h").alias("kernel")), "grp", "left")
    kernels = kernels.select("grp", F.explode(F.sequence(F.lit(0), F.col("chunks") - 1)).alias("chunk"), F.coalesce("kernel", F.array().cast("array<bigint>")).alias("kernel"))
    chunk = F.pmod(F.xxhash64("cls", F.lit(1)), F.col("chunks").cast("long")).cast("int").alias("chunk")  # a group of any size is met in even parts
    met = near.join(held.select("grp", "chunks"), "grp").select("grp", chunk, "cls", "comp", "n").join(sets, "cls").join(kernels, ["grp", "chunk"])
    apart = met.select("grp", "cls", "comp", "n", F.concat(F.array_except("kernel", "shingles"), F.array_except("shingles", "kernel")).alias("d"))
    apart = settle(apart.withColumn("m", F.size("d").cast("long")), "apart")
    stays = lambda cut: F.lit(10) * F.col("m") <= cut * F.col("n")
    # Linked a and b with |d(a)| > c n(a): |d(b)| >= |d(a)| - |a xor b|, n(a) >= t n(b) and |a xor b| <= (1/t - 1) n(b).
    reach = lambda cut: F.lit(10 * num * den) * F.col("m") > F.col("n") * (cut * F.lit(num * num) - F.lit(10 * den * (den - num)))
    plain = who.where("grp < 0").select("cls", "comp", "n")
    anyway = plain.union(apart.where(reach(F.lit(max(CUTS)))).select("cls", "comp", "n")).select("cls").distinct().withColumn("anyway", F.lit(True))  # in group -1 by any cut
    more = lambda cut: F.when(stays(cut), F.col("m")).otherwise(0) + F.when(reach(cut) & F.col("anyway").isNull(), F.col("n")).otherwise(0)
    costs = apart.select("grp", "cls", "n", "m").join(anyway, "cls", "left").groupBy("grp").agg(*(F.sum(more(F.lit(c))).alias(f"cost{c}") for c in CUTS))
    best = F.array_min(F.array(*(F.struct(F.col(f"cost{c}").alias("cost"), F.lit(-c).alias("less")) for c in CUTS)))
    known = apart.join(settle(costs.select("grp", (-best["less"]).alias("cut")), "cuts"), "grp")
    far = settle(plain.union(known.where(reach(F.col("cut"))).select("cls", "comp", "n")).distinct(), "far")  # few ids, joined by their true size
    whole = far.join(sets, "cls").select(F.lit(-1).cast("long").alias("grp"), "cls", "comp", "n", F.col("shingles").alias("d"))
    return settle(known.where(stays(F.col("cut"))).select("grp", "cls", "comp", "n", "d").union(whole), "differences")


def _distant_pairs(lists: DataFrame, sets: DataFrame, num: int, den: int, tasks: int) -> DataFrame:
    """(a, b): pairs of different components within the groups of long lists, as their differences from the kernel allow.

    |a xor b| is |d(a) xor d(b)|, and a link allows (den - num) / (den + num) of n(a) + n(b). Where |d(a)| + |d(b)| is within that, both are linked to the
    member of the group with the most room, so pairs with this one suffice. Otherwise the two share an element of d, as _met() finds it."""
    own = _differences(lists, sets, num, den)
    room = (F.lit(den - num) * F.col("n") - F.lit(den + num) * F.size("d")).alias("room")
    spare = own.where("grp >= 0").select("grp", "cls", "comp", room)
    centre = spare.groupBy("grp").agg(F.max(F.struct("room", "cls", "comp")).alias("c"))
    around = spare.join(centre, "grp").where((F.col("comp") != F.col("c.comp")) & (F.col("room") + F.col("c.room") >= 0)).select(F.col("c.cls").alias("a"), F.col("cls").alias("b"))
    return around.union(_met(own.where("grp >= 0"), num, den, tasks, True)).union(_met(own.where("grp < 0"), num, den, tasks, False))


def _met(own: DataFrame, num: int, den: int, tasks: int, described: bool) -> DataFrame:
    """(a, b): members (grp, cls, comp, n, d) of different components that share one of the first elements of d; described: d is a difference from a kernel.

    As at most (1/t - 1) n(a) elements of d(a) are not in d(b), linked members share one of the first (1/t - 1) n(a) + 1 of either, by any order; of a whole set
    at most (1 - t) n(a) elements are not in the other, so the first (1 - t) n(a) + 1 do. Only a part of all elements, EARLY times (1/t - 1) n(a) by their
    hashes, is counted: of these come those of one component first, which meet nothing, then rare before frequent ones; all others follow by value, where a
    member has too few of that part. The members that an element brings together are compared as in any list: all with those outside the largest component
    there, by the short differences."""
    counted = lambda h: F.pmod(h, F.lit(1000)) < int(1000 * EARLY * (den - num) / num)
    own = own.withColumn("early", F.filter("d", counted))
    told = own.select("grp", "cls", "comp", F.explode("early").alias("h"))
    often = told.groupBy("grp", "h").agg(F.count("*").alias("freq"), F.min("comp").alias("lo"), F.max("comp").alias("hi")).where("lo < hi").select("grp", "h", "freq")
    shared = told.hint("merge").join(often, ["grp", "h"]).groupBy("grp", "cls").agg(F.array_sort(F.collect_list(F.struct("freq", "h"))).alias("own"))
    first = (F.floor(F.lit(den - num) * F.col("n") / F.lit(num if described else den)) + 1).cast("int")
    mine = F.coalesce(F.transform("own", lambda o: o["h"]), F.array().cast("array<bigint>"))
    cols = own.hint("merge").join(shared, ["grp", "cls"], "left").select("grp", "cls", "comp", "n", "d", "early", mine.alias("mine"), first.alias("first"))
    lone, late = F.size("early") - F.size("mine"), F.greatest(F.lit(0), F.col("first") - F.size("early"))
    rest = F.when(late > 0, F.slice(F.array_sort(F.filter("d", lambda h: ~counted(h))), F.lit(1), late)).otherwise(F.array().cast("array<bigint>"))
    taken = F.concat(F.slice("mine", F.lit(1), F.greatest(F.lit(0), F.col("first") - lone)), rest)
    told_apart = F.col("d" if described else "early")  # of whole sets, the counted part: no pair differs there more than on the whole
    ship(own.sparkSession)
    marked = cols.select("grp", "cls", "comp", "n", lone.alias("x"), F.size(told_apart).alias("m"), taken.alias("taken"), told_apart.alias("d"))
    marked = marked.mapInArrow(_marker, "grp long, cls long, comp long, n long, x int, m int, taken array<long>, d array<long>")
    posted = settle(marked.select("grp", F.explode("taken").alias("h"), "cls", "comp", "n", "x", "m", "d").coalesce(tasks), "posted")
    stray, full = _strays(posted, ["grp", "h"], ["cls", "comp", "n", "x", "m", "d"])
    most = F.lit(den - num) * (F.col("n_a") + F.col("n_b"))
    within = F.lit(den + num) * F.greatest(F.abs(F.col("m_a") - F.col("m_b")), _least_difference(F.col("d_a"), F.col("d_b"), num, den)) <= most
    fits = (F.lit(den + num) * (F.col("x_a") + F.col("x_b")) <= most) & within
    return stray.hint("merge").join(full, ["grp", "h"]).where(_apart(num, den) & fits).select(F.col("cls_a").alias("a"), F.col("cls_b").alias("b"))


def _strays(rows: DataFrame, key: list[str], cols: list[str]) -> tuple[DataFrame, DataFrame]:
    """(members outside the largest component of their key, all members with that component) of keys with several components, columns marked _a and _b."""
    parts = rows.groupBy(*key, "comp").agg(F.count("*").alias("c")).groupBy(*key).agg(F.count("*").alias("parts"), F.max_by("comp", F.struct("c", "comp")).alias("key_top"))
    lead = parts.where("parts > 1").select(*key, "key_top")
    known = rows.hint("merge").join(lead, key)
    return known.where("comp <> key_top").select(*key, *(F.col(c).alias(f"{c}_a") for c in cols)), known.select(*key, "key_top", *(F.col(c).alias(f"{c}_b") for c in cols))


def _apart(num: int, den: int):
    """A pair of a stray and a member that is of two components, named once, and of sizes that allow the threshold."""
    once = (F.col("comp_b") == F.col("key_top")) | (F.col("cls_a") < F.col("cls_b"))
    return (F.col("comp_a") != F.col("comp_b")) & once & (F.lit(den) * F.least("n_a", "n_b") >= F.lit(num) * F.greatest("n_a", "n_b"))


def _rest_pairs(member: DataFrame, sets: DataFrame, num: int, den: int, tasks: int) -> DataFrame:
    """(a, b): what the turns left open: in lists of LONG members at most, those outside the largest component with all others; in long lists, the pairs of _distant_pairs()."""
    parts = member.groupBy("e", "comp").agg(F.count("*").alias("c"))
    lead = parts.groupBy("e").agg(F.count("*").alias("parts"), F.max_by("comp", F.struct("c", "comp")).alias("top"), F.max("c").alias("most")).where("parts > 1").select("e", "top", "most")
    open_lists = settle(member.join(lead, "e").coalesce(tasks), "open")
    rest, full = _strays(open_lists.where("not long").select("e", "cls", "comp", "n"), ["e"], ["cls", "comp", "n"])
    near = rest.join(full, "e").where(_apart(num, den)).select(F.col("cls_a").alias("a"), F.col("cls_b").alias("b"))
    return near.union(_distant_pairs(open_lists.where("long"), sets, num, den, tasks))


def near_duplicate_groups(docs: DataFrame, k: int = 5, num: int = 80, den: int = 100, coords: int = 24, stars: int = 2, miss: float = 1e-8) -> DataFrame:
    """docs (doc_id, text) -> one row per document: (doc_id, n_shingles, component_id, kept, text_key), the last a hash of the text.

    Linked: intersection / union of the shingle sets >= num / den. ``component_id`` is the least doc_id of the document's
    component, ``kept`` marks it. Null, empty and blank texts have no shingles and stay alone; equal texts are always
    together; repeated rows are repeated in the result; rows of one doc_id with different texts are separate documents; a null
    doc_id is linked like any other but names a component only if all its ids are null (then null, and kept). No rows give no
    rows. Other columns of docs are ignored."""
    match = match_threshold(coords, num, den, miss)
    signed = settle(sign(docs, k, coords), "signed")
    classes = signed.where("print is not null").groupBy("print").agg(F.min("doc_id").alias("doc_id"), F.first("n").alias("n"), F.first("sig").alias("sig"))
    classes = settle(classes.withColumn("cls", F.monotonically_increasing_id()), "classes")
    lists = settle(_postings(classes, match), "lists")
    sets = settle(_sets(docs, classes.join(lists.select("cls").distinct(), "cls").select("cls", "print", "doc_id"), k), "sets")
    links = roots = None  # of the turns so far
    tasks = -(-lists.count() // POSTINGS_A_TASK) or 1
    for turn in range(stars + 1):
        if roots is None:
            member = lists.withColumn("comp", F.col("cls"))
        else:
            member = settle(lists.join(roots.toDF("cls", "root"), "cls", "left").select("e", "cls", "n", "long", F.coalesce("root", "cls").alias("comp")).coalesce(tasks), "member")
        if turn < stars:
            pairs = _star_pairs(member.where("long") if turn else member, turn)
        else:
            pairs = _rest_pairs(member, sets, num, den, tasks)
        new = settle(_confirmed(pairs, classes, sets, match, num, den, tasks), "links")
        links = new if links is None else links.union(new)
        roots = settle(connected_components(links), "roots")  # (node, root)
    grouped = classes.join(roots.toDF("cls", "root"), "cls", "left").select("print", "doc_id", F.coalesce("root", "cls").alias("comp"))
    least = grouped.groupBy("comp").agg(F.min("doc_id").alias("component_id"))
    named = grouped.join(least, "comp").select("print", "component_id")
    return signed.join(named, "print", "left").select(
        "doc_id", F.col("n").alias("n_shingles"), F.when(F.col("print").isNull(), F.col("doc_id")).otherwise(F.col("component_id")).alias("component_id"), "text_key"
    ).withColumn("kept", F.col("doc_id").eqNullSafe(F.col("component_id")))


def drop_near_duplicates(docs: DataFrame, **how) -> DataFrame:
    """The rows of docs, with all their columns, that their groups keep: one of each group. Of repeated rows one stays; texts without words all stay, but for repeated rows."""
    kept = settle(near_duplicate_groups(docs, **how).where("kept").select("doc_id", "text_key"), "kept")
    once = kept.distinct().alias("once")
    rows = docs.select(F.struct("*").alias("row"), F.col("doc_id").cast("long").alias("doc_id"), F.xxhash64(F.col("text").cast("string")).alias("text_key")).alias("rows")
    own = rows.join(once, F.col("rows.doc_id").eqNullSafe(F.col("once.doc_id")) & (F.col("rows.text_key") == F.col("once.text_key")), "left_semi")
    return (own if kept.count() == once.count() else own.dropDuplicates(["doc_id", "text_key"])).select("row.*")
