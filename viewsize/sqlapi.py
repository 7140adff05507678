"""SQL entry points: temporary views of the tables, SQL functions over hashes, a table function for estimates."""

from __future__ import annotations

import math

from pyspark.sql import Row, SparkSession
from pyspark.sql.functions import udtf

from .operators import counting
from .session import ship

TABLES = ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "documents", "embeddings", "pages", "benchmark", "labels", "conversations")


def register(spark: SparkSession, sf_dir: str | None = None) -> None:
    """vs_hash(seed, name, value), vs_bucket(y, m), vs_rank(y, m, l) and vs_level(y, l) as SQL functions, which the analyzer puts inline; vs_curve(name, m) as a
    table function; viewsize_estimate(TABLE(...), m) as a table function over a table; the tables of sf_dir as views."""
    ship(spark)
    if sf_dir:
        for t in TABLES:
            spark.read.parquet(f"{sf_dir}/{t}.parquet").createOrReplaceTempView(t)
    for text in (
        "vs_hash(seed BIGINT, name STRING, v STRING) RETURNS BIGINT RETURN xxhash64(seed, name, CAST(v IS NULL AS INT), v)",
        "vs_bucket(y BIGINT, m BIGINT) RETURNS BIGINT RETURN y & (m - 1)",
        "vs_rest(y BIGINT, m BIGINT) RETURNS BIGINT RETURN shiftrightunsigned(y, CAST(log2(m) AS INT))",
        "vs_zeros(w BIGINT) RETURNS INT RETURN bit_count((w & -w) - 1)",
        "vs_rank(y BIGINT, m BIGINT, l INT) RETURNS INT RETURN least(vs_zeros(vs_rest(y, m)), l - CAST(log2(m) AS INT)) + 1",
        "vs_level(y BIGINT, l INT) RETURNS INT RETURN CASE WHEN y = 0 THEN l WHEN y = -9223372036854775807 - 1 THEN 63 ELSE vs_zeros(CASE WHEN y = -9223372036854775807 - 1 THEN 1 ELSE y END) END",
    ):
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {text}")
    spark.udtf.register("vs_curve", TheoryCurve)
    spark.udtf.register("viewsize_estimate", ViewSizeEstimate)


@udtf(returnType="m bigint, value double")
class TheoryCurve:
    """Rows (m, value) of a standard-error curve for powers of two from 16 to ``top``."""

    def eval(self, curve: str, top: int):
        factor = {"rse_pc": 0.78, "rse_ll": 1.3, "lps_short": 5.0}[curve]
        m = 16
        while m <= top:
            yield m, factor / math.sqrt(m)
            m *= 2


@udtf(returnType="facts bigint, beta bigint, branch string, estimate double")
class ViewSizeEstimate:
    """viewsize_estimate(TABLE(SELECT ...) [PARTITION BY ...] , m): Adaptive Counting of the rows of a table argument, or of each of its partitions. Rows pass through
    Python one by one; over large tables the DataFrame entry points, or ac_sql(), do the same by expressions."""

    def __init__(self):
        self.registers, self.facts, self.m = None, 0, 0

    def eval(self, row: Row, m: int):
        import xxhash

        if self.registers is None:
            if m < 2 or m & (m - 1):
                raise ValueError("m must be a power of two from 2 on")
            self.m, self.registers = m, [0] * m
        y = xxhash.xxh64_intdigest(repr(tuple(row)).encode("utf-8", "surrogatepass"))
        k = self.m.bit_length() - 1
        rest = y >> k
        rank = (rest & -rest).bit_length() if rest else 64 - k + 1
        self.registers[y & (self.m - 1)] = max(self.registers[y & (self.m - 1)], rank)
        self.facts += 1

    def terminate(self):
        if self.registers is not None:
            beta, m = self.registers.count(0), self.m
            if beta / m >= counting.SWITCH:
                yield self.facts, beta, "linear", -m * math.log(beta / m)
            else:
                yield self.facts, beta, "loglog", counting.alpha(m) * m * 2.0 ** (sum(self.registers) / m)


def ac_sql(table: str, dims: list[str], m: int = 2048, seed: int = 0) -> str:
    """Adaptive Counting of a view as one SQL statement over the registered functions."""
    k = int(math.log2(m))
    alpha = 0.39701 - (2 * math.pi**2 + math.log(2) ** 2) / (48 * m)
    h = " ^ ".join(f"vs_hash({seed}, '{d}', CAST({d} AS STRING))" for d in dims)
    return f"""
WITH hashed AS (SELECT xxhash64({h}) AS y FROM {table}),
regs AS (SELECT vs_bucket(y, {m}) AS bucket, max(vs_rank(y, {m}, 64)) AS reg FROM hashed GROUP BY 1),
total AS (SELECT sum(reg) AS a, {m} - count(*) AS beta FROM regs)
SELECT a, beta, CASE WHEN beta / {m}.0D >= 0.051D THEN -{m}.0D * ln(beta / {m}.0D) ELSE {alpha * m!r}D * pow(2.0D, a / {m}.0D) END AS estimate, {k} AS k FROM total"""
