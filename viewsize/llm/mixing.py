"""Mixing sources to target weights over fixed-length token blocks.

Each source's documents, in a hashed order, form one stream of words that is cut into blocks of ``block`` words. A source's
quota of words is met in epochs: in each, the full blocks come in a pseudorandom order of their own (a keyed Feistel network
on block numbers, so nothing is stored or sorted), then the short last one; the last slot of all is cut short where the quota
ends. Output shards get multinomial source counts, drawn under the condition that they add up to the quotas: a tree of
hypergeometric halvings, in which every shard finds its own counts and its first slot of each source from the seed alone. Slots
become block numbers in parallel, and blocks meet documents in one equi-join by (source, block).

Gathered to the driver, and broadcast: one row for each source, nothing that grows with documents or blocks.
"""

from __future__ import annotations

import math
import re

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..session import ship
from .common import WORD, settle, words

_CHUNK_ROWS = 20_000
#: Below this population numpy draws.
_NUMPY_MOST = 1_000_000_000
_SLOTS_A_SHARD = 4096
# Odd multipliers of the round function.
_ROUND = (0x9E3779B97F4A7C15, 0xC2B2AE3D27D4EB4F, 0x165667B19E3779F9, 0xD6E8FEB86659FD93)


def targets(sizes: list[int], weights: list[float], most: float = 3.0) -> list[float]:
    """Shares of the sum of sizes by weight, none above ``most`` times its size; what a stopped one leaves is shared again by weight."""
    out, total = [0.0] * len(sizes), float(sum(sizes))
    active = sorted(range(len(sizes)), key=lambda i: (most * sizes[i] / weights[i], i))
    left, mass = total, float(sum(weights))
    for at, i in enumerate(active):
        if most * sizes[i] * mass > left * weights[i]:
            for j in active[at:]:
                out[j] = left * weights[j] / mass
            break
        out[i] = most * sizes[i]
        left, mass = left - out[i], mass - weights[i]
    return out


def permute(x: np.ndarray, n: int, key: int) -> np.ndarray:
    """A pseudorandom permutation of 0..n-1, by position: a four-round Feistel network on the least even number of bits, walked until it is below n."""
    if n <= 1:
        return x.copy()
    half = max(1, (int(n - 1).bit_length() + 1) // 2)
    mask = np.uint64((1 << half) - 1)
    out, todo = x.astype(np.uint64), np.arange(len(x))
    while len(todo):
        left, right = out[todo] >> np.uint64(half), out[todo] & mask
        for i, c in enumerate(_ROUND):
            f = (right + np.uint64((key * 0x2545F491 + i * 0x9E3779B1) & 0xFFFFFFFF)) * np.uint64(c)
            f ^= f >> np.uint64(31)
            f *= np.uint64(_ROUND[3 - i])
            left, right = right, left ^ ((f >> np.uint64(33)) & mask)
        out[todo] = (left << np.uint64(half)) | right
        todo = todo[out[todo] >= n]
    return out.astype(np.int64)


def _log_choose_term(x: float, n: float, p: float) -> float:
    """Logarithm of the binomial probability of x of n at rate p, by the saddle-point form, which keeps its precision at any size."""
    if x == 0 or x == n:
        return n * (math.log1p(-p) if x == 0 else math.log(p))

    def rest(k: float) -> float:  # ln k! less Stirling's formula
        if k < 16:
            return math.lgamma(k + 1) - (k + 0.5) * math.log(k) + k - 0.5 * math.log(2 * math.pi)
        return (1 / 12 - (1 / 360 - (1 / 1260 - 1 / 1680 / (k * k)) / (k * k)) / (k * k)) / k

    def deviance(x: float, m: float) -> float:  # x ln(x / m) + m - x
        if abs(x - m) < 0.1 * (x + m):
            v = (x - m) / (x + m)
            total, term, j = (x - m) * v, 2 * x * v, 1
            while True:
                term *= v * v
                after = total + term / (2 * j + 1)
                if after == total:
                    return after
                total, j = after, j + 1
        return x * math.log(x / m) + m - x

    q = 1 - p
    out = rest(n) - rest(x) - rest(n - x) - deviance(x, n * p) - deviance(n - x, n * q)
    return out + 0.5 * math.log(n / (2 * math.pi * x * (n - x)))


def hypergeometric(good: int, bad: int, take: int, rng: np.random.Generator) -> int:
    """How many of ``take`` draws without replacement are good, of populations of any size: numpy's draw within its range, beyond it the ratio of uniforms (Stadlober)
    with exact logarithms of the probabilities."""
    total = good + bad
    low, high = max(0, take - bad), min(good, take)
    if low == high:
        return low
    if total < _NUMPY_MOST:
        return int(rng.hypergeometric(good, bad, take))
    rate = take / total

    def log_p(x: int) -> float:
        return _log_choose_term(x, good, rate) + _log_choose_term(take - x, bad, rate)  # but for a constant

    mode = min(high, max(low, (take + 1) * (good + 1) // (total + 2)))
    top = log_p(mode)
    mean, spread = take * (good / total), math.sqrt(take * (good / total) * (bad / total) * ((total - take) / (total - 1)) + 0.5)
    width = 2 * math.sqrt(2 / math.e) * spread + 3 - 2 * math.sqrt(3 / math.e)
    while True:
        u, v = rng.random(), rng.random()
        x = math.floor(mean + 0.5 + width * (v - 0.5) / max(u, 1e-300))
        if low <= x <= high and 2 * math.log(max(u, 1e-300)) <= log_p(x) - top:
            return x


def _half(counts: np.ndarray, take: int, rng: np.random.Generator) -> np.ndarray:
    """``take`` of all slots drawn without replacement, by source: each source's share of what the ones before it have left."""
    out, left = np.zeros_like(counts), int(counts.sum())
    for i, n in enumerate(counts.tolist()):
        left -= n
        out[i] = hypergeometric(n, left, take, rng)
        take -= int(out[i])
    return out


def shard_counts(quota: np.ndarray, shard: int, shards: int, slots: int, seed: int) -> tuple[np.ndarray, np.ndarray]:
    """(first, count) by source of one output shard of ``slots`` slots (the last: what is left)."""
    lo, hi, first, counts = 0, shards, np.zeros(len(quota), np.int64), np.asarray(quota, np.int64)
    while hi - lo > 1:
        mid = (lo + hi) // 2
        left = _half(counts, min(int(counts.sum()), (mid - lo) * slots), np.random.default_rng((seed, lo, hi)))
        if shard < mid:
            hi, counts = mid, left
        else:
            lo, first, counts = mid, first + left, counts - left
    return first, counts


class Plan:
    """What the driver knows: for each source its words, target, quota, full blocks, short block and slots."""

    def __init__(self, sources: list[tuple[str | None, int]], block: int, most: float, seed: int):
        order = sorted(sources, key=lambda s: (s[0] is None, (s[0] or "").encode("utf-8", "surrogatepass")))
        self.names, self.block, self.seed = [s[0] for s in order], block, seed
        self.sizes = [int(s[1]) for s in order]
        self.targets = targets(self.sizes, [1.0 + i % 3 for i in range(len(order))], most)
        self.quota = [min(int(most * s), round(t)) for s, t in zip(self.sizes, self.targets)]
        self.full = [s // block for s in self.sizes]
        self.slots = []
        for s, q, f in zip(self.sizes, self.quota, self.full):
            whole, rest = divmod(q, s) if s else (0, 0)
            self.slots.append(whole * (f + (s % block > 0)) + -(-rest // block))
        self.shards = max(1, -(-sum(self.slots) // _SLOTS_A_SHARD))

    def blocks(self, i: int, at: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(epoch, block number, words taken) of slots of source i."""
        tail = self.sizes[i] % self.block
        each, full = self.full[i] + (tail > 0), self.full[i]
        epoch, pos = at // each, at % each
        number = pos.copy()
        for e in np.unique(epoch):
            own = (epoch == e) & (pos < full)
            number[own] = permute(pos[own], full, self.seed * 1_000_003 + i * 8191 + int(e))
        take = np.where(pos < full, self.block, tail)
        whole, rest = divmod(self.quota[i], self.sizes[i])
        if rest:
            last = at == self.slots[i] - 1
            take[last] = np.minimum(take[last], rest - pos[last] * self.block)
        return epoch, number, take


def _drawer(plan: Plan):
    def run(batches):
        for batch in batches:
            for shard in batch.column(0).to_pylist():
                first, counts = shard_counts(np.array(plan.slots, np.int64), shard, plan.shards, _SLOTS_A_SHARD, plan.seed)
                for i in np.flatnonzero(counts):
                    at = np.arange(first[i], first[i] + counts[i])
                    epoch, number, take = plan.blocks(int(i), at)
                    n = len(at)
                    yield pa.RecordBatch.from_arrays(
                        [pa.array(np.full(n, shard)), pa.array(np.full(n, i, np.int32)), pa.array(at), pa.array(epoch.astype(np.int32)), pa.array(number), pa.array(take)],
                        names=["shard", "source_no", "slot", "epoch", "block", "take"],
                    )

    return run


def mix_rows(docs: DataFrame, block: int = 512, most: float = 3.0, seed: int = 17) -> tuple[DataFrame, DataFrame, Plan]:
    """docs with (n, doc_id, source, size, text_key), n a row number of any kind -> (rows with source_no and start, draws (n, shard, epoch, a, b), plan):
    each draw takes the words a to b (end excluded) of row n."""
    spark = docs.sparkSession
    ship(spark)
    rows = docs.select("n", "doc_id", "source", "size", "text_key")
    per = rows.groupBy("source").agg(F.sum("size").alias("size"), F.count("*").alias("rows")).collect()
    plan = Plan([(r["source"], r["size"]) for r in per], block, most, seed)
    count = {r["source"]: r["rows"] for r in per}
    numbered = [(name, i, plan.sizes[i], plan.targets[i], -(-count[name] // _CHUNK_ROWS)) for i, name in enumerate(plan.names)]
    table = F.broadcast(spark.createDataFrame(numbered, "source string, source_no int, source_size long, target double, chunks int"))
    key = F.xxhash64(F.lit(seed), "doc_id", "text_key")  # not the row number: it hangs on how files are split
    rows = rows.join(table, rows["source"].eqNullSafe(table["source"])).drop(table["source"])
    rows = settle(rows.withColumn("chunk", F.pmod(key, F.col("chunks").cast("long"))), "chunked")
    sums = rows.groupBy("source_no", "chunk").agg(F.sum("size").alias("words"))
    base = sums.select("source_no", "chunk", (F.sum("words").over(Window.partitionBy("source_no").orderBy("chunk")) - F.col("words")).alias("base"))  # one row per 20,000 documents
    within = Window.partitionBy("source_no", "chunk").orderBy(key, "n")
    rows = rows.withColumn("start", F.sum("size").over(within) - F.col("size")).join(base, ["source_no", "chunk"])
    rows = settle(rows.withColumn("start", F.col("start") + F.col("base")).drop("base", "chunk", "chunks", "text_key"), "streams")
    shards = spark.range(0, plan.shards if sum(plan.slots) else 0, numPartitions=max(1, min(plan.shards, 20_000)))
    # Written first: from a few shard numbers the planner would guess a side small enough to broadcast.
    draws = settle(shards.mapInArrow(_drawer(plan), "shard long, source_no int, slot long, epoch int, block long, take long"), "draws")
    b = F.lit(block)
    part = rows.where("size > 0").select(
        "n", "source_no", "start", "size", F.explode(F.sequence(F.floor(F.col("start") / b).cast("long"), F.floor((F.col("start") + F.col("size") - 1) / b).cast("long"))).alias("block")
    )
    met = draws.join(part, ["source_no", "block"]).select(
        "n", "shard", "slot", "epoch", F.greatest(F.lit(0), F.col("block") * b - F.col("start")).alias("a"), F.least("size", F.col("block") * b + F.col("take") - F.col("start")).alias("b")
    )
    return rows, met.where("a < b"), plan


def _numbered(docs: DataFrame, name: str, *more: str) -> DataFrame:
    text = F.col("text").cast("string")
    cols = [c for c in more if c not in ("doc_id", "source")]
    return settle(
        docs.select(F.monotonically_increasing_id().alias("n"), F.col("doc_id").cast("long").alias("doc_id"), F.col("source").cast("string").alias("source"), words(text).alias("size"), F.xxhash64(text).alias("text_key"), *cols), name
    )


def mixture_report(docs: DataFrame, block: int = 512, seed: int = 17) -> DataFrame:
    """docs (doc_id, text, source) -> one row per document: (doc_id, size, source_size, target, taken).

    Sources in code-point order, null last, weigh 1, 2, 3, repeating; targets stop at 3 times a source's words. ``taken`` adds up what the mix takes
    of the document, repeats counted: over a source it equals the target, rounded, and no document gives more than 3 times its words. Null texts and
    texts without words have size 0 and give nothing; repeated rows and null ids are mixed like any other row; no rows give no rows; other columns are ignored.
    Reruns over the same files agree."""
    rows, draws, _ = mix_rows(_numbered(docs, "sizes"), block, seed=seed)
    taken = draws.groupBy("n").agg(F.sum(F.col("b") - F.col("a")).alias("taken"))
    return rows.join(taken, "n", "left").select("doc_id", "size", "source_size", "target", F.coalesce("taken", F.lit(0)).cast("long").alias("taken"), "source")


_FIND = re.compile(WORD.encode())


def cut(text: str, spans: list[tuple[int, int]], size: int) -> str:
    """The words of the spans, verbatim with what stands between them; neighbouring spans are joined, others set apart by a line feed. All words: the text itself."""
    merged: list[list[int]] = []
    for a, b in sorted(spans):
        if merged and a <= merged[-1][1]:
            merged[-1][1] = max(b, merged[-1][1])
        else:
            merged.append([a, b])
    if merged == [[0, size]]:
        return text
    raw = text.encode("utf-8", "surrogatepass")
    at = [m.span() for m in _FIND.finditer(raw)]
    return b"\n".join(raw[at[a][0] : at[b - 1][1]] for a, b in merged).decode("utf-8", "surrogatepass")


def _cutter(batches):
    for batch in batches:
        texts = [cut(t, list(zip(a, b)), n) for t, a, b, n in zip(*(batch.column(c).to_pylist() for c in ("text", "a", "b", "size")))]
        yield pa.RecordBatch.from_arrays(
            [batch.column("doc_id"), pa.array(texts, pa.string()), batch.column("lang"), batch.column("source"), pa.array([len(t) for t in texts], pa.int64())],
            names=["doc_id", "text", "lang", "source", "n_chars"],
        )


def mix_documents(docs: DataFrame, block: int = 512, seed: int = 17) -> DataFrame:
    """docs (doc_id, text, lang, source) -> the mix as (doc_id, text, lang, source, n_chars): a row for each document and epoch that the mix takes words of,
    with those words. Documents that it takes nothing of, and those without words, are not in it."""
    ship(docs.sparkSession)
    numbered = _numbered(docs, "numbered", "text", "lang")
    _, draws, _ = mix_rows(numbered, block, seed=seed)
    spans = draws.groupBy("n", "epoch").agg(F.collect_list(F.struct("a", "b")).alias("s"))  # at most the blocks of one document
    met = numbered.join(spans, "n").select("doc_id", "text", F.col("lang").cast("string").alias("lang"), "source", "size", F.col("s.a").alias("a"), F.col("s.b").alias("b"))
    return met.mapInArrow(_cutter, "doc_id long, text string, lang string, source string, n_chars long")
