"""Variable-capacity best-fit packing of documents into sequences.

Items are documents, those longer than the largest sequence cut into pieces. Best-fit-decreasing depends on the sizes alone, so
it runs on the histogram of sizes, which has at most as many entries as the largest capacity has words, however many
documents there are. Bins that look alike are handled as one interval of bin numbers: items of one size go into the interval
with the least room that takes them, an interval splits where items run out, and a new interval is opened at the
permitted capacity of least cost. The plan is a table of runs (size, first rank, items, first bin, items a bin, offset); each item
finds its run by its rank within its size. At the end every bin shrinks to the least permitted capacity that holds it.
"""

from __future__ import annotations

from bisect import bisect_left, insort
from collections import defaultdict

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..session import ship
from .common import settle, words

CAPACITIES = (512, 1024, 2048, 4096)
#: A sequence of c words costs c, a fixed number of words, and c * c over a divisor: attention grows with the square.
FIXED_COST, ATTENTION = 32, 16_384


def cost(capacity: int, fixed: float = FIXED_COST, attention: float = ATTENTION) -> float:
    return capacity + fixed + capacity * capacity / attention


_CHUNK_ROWS = 20_000


class _Open:
    """Intervals of bins with equal room, by room."""

    def __init__(self) -> None:
        self.by_room: dict[int, list] = defaultdict(list)
        self.rooms: list[int] = []

    def add(self, room: int, interval: tuple[int, int, int]) -> None:
        if room > 0 and not self.by_room[room]:
            insort(self.rooms, room)
        self.by_room[room].append(interval)

    def tightest(self, size: int):
        at = bisect_left(self.rooms, size)
        if at == len(self.rooms):
            return None
        room = self.rooms[at]
        interval = self.by_room[room].pop()
        if not self.by_room[room]:
            del self.rooms[at]
        return room, interval


def _opening(size: int, n: int, smaller: int, costs: dict[int, float]) -> int:
    """The capacity whose cost per word is least, if the rest of a bin is filled as far as the words in smaller items go."""
    best, least = 0, float("inf")
    for c, price in costs.items():
        if c >= size:
            each = min(n, c // size)
            bins = -(-n // each)
            fill = each * size + min(c - each * size, smaller / bins)
            if price / fill < least - 1e-12:
                best, least = c, price / fill
    return best


def pack_histogram(counts: dict[int, int], capacities: tuple[int, ...] = CAPACITIES, fixed: float = FIXED_COST, attention: float = ATTENTION) -> tuple[list[tuple], list[tuple], float]:
    """size -> number of items; gives runs (size, rank, items, bin, each, offset), bins (first, end, used, capacity) and the cost.

    All prefixes of the permitted capacities that hold the largest item are tried, and the cheapest result after downsizing is kept."""
    capacities = tuple(sorted(set(capacities)))
    sizes = sorted((s for s, n in counts.items() if n and s > 0), reverse=True)
    if not sizes:
        return [], [], 0.0
    costs = {c: cost(c, fixed, attention) for c in capacities}
    tried = [_pack(sizes, counts, capacities[:i], costs) for i in range(1, len(capacities) + 1) if capacities[i - 1] >= sizes[0]]
    return min(tried, key=lambda t: t[2])


def _pack(sizes: list[int], counts: dict[int, int], allowed: tuple[int, ...], costs: dict[int, float]) -> tuple[list[tuple], list[tuple], float]:
    capacities = tuple(costs)
    runs, open_, end = [], _Open(), 0
    smaller = sum(s * counts[s] for s in sizes)
    for size in sizes:
        left, rank = counts[size], 0
        smaller -= size * left
        while left:
            found = open_.tightest(size)
            if found is None:
                c = _opening(size, left, smaller, {c: costs[c] for c in allowed})
                each = min(left, c // size)
                bins = left // each
                runs.append((size, rank, bins * each, end, each, 0))
                open_.add(c - each * size, (end, end + bins, each * size))
                end, rank, left = end + bins, rank + bins * each, left - bins * each
                continue
            room, (lo, hi, used) = found
            each = room // size  # a bin that can take another of the same size is then the tightest
            bins = min(hi - lo, left // each)
            if not bins:
                each, bins = left, 1
            runs.append((size, rank, bins * each, lo, each, used))
            open_.add(room - each * size, (lo, lo + bins, used + each * size))
            if lo + bins < hi:
                open_.add(room, (lo + bins, hi, used))
            rank, left = rank + bins * each, left - bins * each
    bins = sorted((lo, hi, used, capacities[bisect_left(capacities, used)]) for held in open_.by_room.values() for lo, hi, used in held)
    return runs, bins, float(sum((hi - lo) * costs[c] for lo, hi, _, c in bins))


def pack_documents(docs: DataFrame, capacities: tuple[int, ...] = CAPACITIES, fixed: float = FIXED_COST, attention: float = ATTENTION) -> DataFrame:
    """docs (doc_id, text) -> one row per piece: (doc_id, piece, first_word, n_words, bin, bin_offset, capacity, bin_words).

    A document longer than the largest capacity is cut into pieces of that many words and a rest; a piece holds the words first_word to
    first_word + n_words of its document and stands at bin_offset of its bin, whose pieces neither overlap nor leave gaps. Documents without
    words (null, empty, blank) keep one row with no bin (nulls) and n_words 0. Repeated rows and null ids are packed like any other; ties are in order of
    doc_id; no rows give no rows; other columns are ignored."""
    spark, top = docs.sparkSession, max(capacities)
    ship(spark)
    size = words(F.col("text").cast("string"))
    rows = settle(docs.select(F.monotonically_increasing_id().alias("n"), F.col("doc_id").cast("long").alias("doc_id"), size.alias("words")), "sizes")
    piece = F.explode(F.sequence(F.lit(0).cast("long"), F.greatest(F.lit(0).cast("long"), F.floor((F.col("words") - 1) / top).cast("long"))))
    items = rows.select("n", "doc_id", "words", piece.alias("piece")).select(
        "n", "doc_id", "piece", (F.col("piece") * top).alias("first_word"), F.least(F.lit(top), F.col("words") - F.col("piece") * top).cast("long").alias("n_words")
    )
    items = items.withColumn("chunk", F.pmod(F.xxhash64("doc_id", "n", "piece"), F.lit(max(1, -(-rows.count() // _CHUNK_ROWS)))))
    # At most max(capacities) sizes: the histogram and the plan are bounded by parameters.
    hist = {r["n_words"]: r["count"] for r in items.where("n_words > 0").groupBy("n_words").count().collect()}
    runs, bins, _ = pack_histogram(hist, capacities, fixed, attention)
    grouped = defaultdict(list)
    for run in runs:
        grouped[run[0]].append(run[1:])
    by_size = {s: np.array(v, np.int64) for s, v in grouped.items()}
    shared = spark.sparkContext.broadcast((by_size, np.array(bins, np.int64).reshape(-1, 4)))
    # Rank within a size in two steps, so that a common size is not one task: counts of hashed chunks first, then order within a chunk.
    counted = items.where("n_words > 0").groupBy("n_words", "chunk").agg(F.count("*").alias("c"))
    base = counted.select("n_words", "chunk", (F.sum("c").over(Window.partitionBy("n_words").orderBy("chunk")) - F.col("c")).alias("base"))  # one row per chunk and size
    ranked = items.withColumn("r", F.row_number().over(Window.partitionBy("n_words", "chunk").orderBy("doc_id", "n", "piece")) - 1)
    ranked = ranked.join(base, ["n_words", "chunk"], "left")
    ranked = ranked.select("doc_id", "piece", "first_word", "n_words", (F.col("r") + F.col("base")).alias("rank"))

    def locate(batches):
        plan, ends = shared.value
        for batch in batches:
            n = batch.column("n_words").to_numpy()
            rank = batch.column("rank").fill_null(0).to_numpy()
            out = np.zeros((len(n), 4), np.int64)
            for s in np.unique(n[n > 0]):
                own, runs = np.flatnonzero(n == s), plan[int(s)]
                r = runs[np.searchsorted(runs[:, 0], rank[own], side="right") - 1]
                i = rank[own] - r[:, 0]
                out[own, 0] = r[:, 2] + i // r[:, 3]
                out[own, 1] = r[:, 4] + i % r[:, 3] * s
            if len(ends):
                at = np.searchsorted(ends[:, 0], out[:, 0], side="right") - 1
                out[:, 2], out[:, 3] = ends[at, 3], ends[at, 2]
            none = n == 0
            yield pa.RecordBatch.from_arrays([*batch.columns[:4], *(pa.array(out[:, i], mask=none) for i in range(4))], names=[*batch.schema.names[:4], "bin", "bin_offset", "capacity", "bin_words"])

    return ranked.mapInArrow(locate, "doc_id long, piece long, first_word long, n_words long, bin long, bin_offset long, capacity long, bin_words long")
