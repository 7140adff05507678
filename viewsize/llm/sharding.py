"""Shards by vector bin packing over bytes, tokens and rows.

The unit is a group of equal texts. The rule, heaviest first, each into the shard where the dot product of its vector with the residual capacity is
highest, is sequential, so it runs on classes of groups: groups whose bytes, tokens and rows fall into the same steps of a logarithmic grid are alike but for
a fraction, and a class is dealt as that many groups of its exact mean. The result of dealing them one by one is found at once, as a level to which the
shards' dot products sink. A group finds its shard by its rank in its class. Groups heavier than a grain are classes of their own, cut by row
hash into pieces where they outweigh a set share of a shard. The number of classes is bounded by the grid, that of heavy groups by the
grain: the driver sees nothing that grows with documents or groups.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..session import ship
from .common import settle, words

DIMENSIONS = ("size", "tokens", "rows")
#: What a dimension counts in the dot product (squared: both factors carry it); the law is on bytes, so they come first.
WEIGHTS = np.array([2.0, 1.0, 1.0])
#: Steps of the grid to a doubling.
STEPS = 4
_CHUNK_ROWS = 20_000


def deal(scores: np.ndarray, step: float, n: int) -> np.ndarray:
    """How many of n equal items each shard gets, if each goes where the score is highest (ties: lowest shard) and lowers it there by ``step``."""
    out = np.zeros(len(scores), np.int64)
    if n > 4 * len(scores):
        count = lambda level: np.maximum(0, np.floor((scores - level) / step) + 1)
        low, high = float(scores.max()) - step * (n + 1), float(scores.max())
        for _ in range(100):
            mid = (low + high) / 2
            low, high = (mid, high) if count(mid).sum() > n else (low, mid)
        out = count(high).astype(np.int64)
    for _ in range(n - int(out.sum())):
        out[int((scores - step * out).argmax())] += 1
    return out


def place_classes(items: np.ndarray, counts: np.ndarray, shards: int) -> np.ndarray:
    """items (n, d), in units of their totals, each for ``counts`` equal ones -> (n, shards) of how many go where. Items go heaviest first (by their largest
    dimension, ties by position)."""
    out = np.zeros((len(items), shards), np.int64)
    left = np.tile((items * counts[:, None]).sum(axis=0) / shards, (shards, 1))
    for i in np.lexsort((np.arange(len(items)), -items.max(axis=1))):
        out[i] = deal(left @ items[i], float(items[i] @ items[i]), int(counts[i]))
        left -= out[i][:, None] * items[i]
    return out


def place(items: np.ndarray, shards: int) -> np.ndarray:
    """The shard of each single item."""
    return place_classes(items, np.ones(len(items), np.int64), shards).argmax(axis=1)


def _sums() -> list[Column]:
    return [F.sum("size").alias("size"), F.sum("tokens").alias("tokens"), F.count("*").alias("rows")]


def _ranked(rows: DataFrame, by: list[str], spread: Column, order: list, n: int) -> DataFrame:
    """rows with ``rank``, from 0 without gaps within ``by``: order within hashed chunks of about 20,000 rows, after the counts of the chunks before."""
    rows = rows.withColumn("chunk", F.pmod(spread, F.lit(max(1, -(-n // _CHUNK_ROWS)))))
    counted = rows.groupBy(*by, "chunk").agg(F.count("*").alias("c"))
    base = counted.select(*by, "chunk", (F.sum("c").over(Window.partitionBy(*by).orderBy("chunk")) - F.col("c")).alias("base"))  # one row a chunk
    within = F.row_number().over(Window.partitionBy(*by, "chunk").orderBy(*order)) - 1
    return rows.withColumn("r", within).join(base, [*by, "chunk"]).withColumn("rank", F.col("r") + F.col("base")).drop("chunk", "r", "base")


def _step(d: str) -> Column:
    return F.floor(F.lit(float(STEPS)) * F.log2(F.col(d) + F.lit(1.0))).cast("int")


def _dealt(rows: DataFrame, shards: int, parcels: int, pieces_a_shard: int) -> DataFrame:
    """rows with (group, size, tokens) -> the same with ``shard``."""
    spark = rows.sparkSession
    groups = settle(rows.groupBy("group").agg(*_sums()), "groups")
    total = groups.agg(*[F.sum(d).alias(d) for d in DIMENSIONS], F.count("*").alias("groups")).first()
    grain = {d: max(1.0, (total[d] or 0) / parcels) for d in DIMENSIONS}
    most = {d: max(1.0, (total[d] or 0) / (shards * pieces_a_shard)) for d in DIMENSIONS}
    heavy = " or ".join(f"{d} > {g!r}" for d, g in grain.items())
    # Fewer than 3 * parcels groups can exceed a grain in one of three dimensions: this is what is gathered and broadcast.
    pieces = F.least(F.col("rows"), F.ceil(F.greatest(*(F.col(d) / F.lit(m) for d, m in most.items())))).cast("int")
    own = sorted((r["group"], r["pieces"]) for r in groups.where(heavy).select("group", pieces.alias("pieces")).collect())
    first, starts = 0, []
    for group, n in own:
        starts.append((group, first, n))
        first += n
    table = F.broadcast(spark.createDataFrame(starts, "group long, first long, pieces int"))
    piece = F.pmod(F.xxhash64(F.lit(1), "doc_id", "n"), F.col("pieces").cast("long"))
    single = rows.join(table, "group").withColumn("item", F.col("first") + piece).drop("first", "pieces")
    items = single.groupBy("item").agg(*_sums()).orderBy("item").collect()
    # The classes of all other groups: as many as the grid has cells that occur.
    light = groups.where(f"not ({heavy})").withColumns({f"step_{d}": _step(d) for d in DIMENSIONS})
    steps = [f"step_{d}" for d in DIMENSIONS]
    cells = light.groupBy(*steps).agg(*[F.sum(d).alias(d) for d in DIMENSIONS], F.count("*").alias("groups")).orderBy(*steps).collect()
    counts = np.array([1] * len(items) + [r["groups"] for r in cells], np.int64)
    vectors = np.array([[float(r[d]) for d in DIMENSIONS] for r in [*items, *cells]]).reshape(len(counts), 3)
    put = place_classes(vectors / np.maximum(counts, 1)[:, None] / np.maximum(vectors.sum(axis=0), 1.0) * WEIGHTS, counts, shards)
    at = spark.createDataFrame([(r["item"], int(s)) for r, s in zip(items, put.argmax(axis=1))], "item long, shard int")
    runs = []
    for r, n in zip(cells, put[len(items) :]):
        used = np.flatnonzero(n)
        runs.append((*(r[c] for c in steps), (np.cumsum(n[used]) - n[used]).tolist(), used.tolist()))
    plan = spark.createDataFrame(runs, ", ".join(f"{c} int" for c in steps) + ", starts array<long>, shards array<int>")
    ranked = _ranked(light.select("group", *steps), steps, F.xxhash64(F.lit(2), "group"), [F.xxhash64(F.lit(3), "group"), "group"], total["groups"])
    found = ranked.join(F.broadcast(plan), steps).select("group", F.element_at("shards", F.size(F.filter("starts", lambda s: s <= F.col("rank")))).alias("shard"))
    cols = ("doc_id", "size", "tokens", "text_crc32", "n", "shard")
    return single.join(F.broadcast(at), "item").select(*cols).union(rows.join(table, "group", "left_anti").join(found, "group").select(*cols))


def shard_documents(docs: DataFrame, shards: int = 40, parcels: int = 4096, pieces_a_shard: int = 2, overhead: int = 16) -> DataFrame:
    """docs (doc_id, text) -> one row per document: (doc_id, size, tokens, text_crc32, law, shard, slot, grown_shard).

    ``size`` is the text's UTF-8 bytes plus ``overhead``; law is 'bytes', so grown_shard is null. Equal texts share a shard unless together
    they outweigh 1/pieces_a_shard of it in bytes, tokens or rows, when their rows are dealt by id hash into pieces of about that weight; groups above
    1/parcels of the whole are placed each by its own vector, the others by their class's. ``slot`` counts from 0 without gaps in
    each shard (rows that tie are interchangeable). Null texts count as empty and are in one group with them; null ids and repeated
    rows are placed like any other; no rows give no rows; other columns are ignored."""
    ship(docs.sparkSession)
    text = F.coalesce(F.col("text").cast("string"), F.lit(""))
    rows = settle(
        docs.select(
            F.col("doc_id").cast("long").alias("doc_id"), F.xxhash64(text).alias("group"), (F.octet_length(text) + overhead).cast("long").alias("size"),
            words(text).alias("tokens"), F.crc32(text.cast("binary")).alias("text_crc32"), F.monotonically_increasing_id().alias("n"),
        ),
        "rows",
    )
    dealt = settle(_dealt(rows, shards, parcels, pieces_a_shard), "dealt")
    ranked = _ranked(dealt, ["shard"], F.xxhash64(F.lit(4), "doc_id", "n"), ["doc_id", "size", "text_crc32", "n"], dealt.count())
    return ranked.select("doc_id", "size", "tokens", "text_crc32", F.lit("bytes").alias("law"), "shard", F.col("rank").cast("long").alias("slot"), F.lit(None).cast("int").alias("grown_shard"))
