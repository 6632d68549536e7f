"""Generator of clustered codes: seeds per cluster, copies with variation, copies as seeds of later ones.

Every code follows from hashes of (seed, record, step, position) alone. A record's ancestors are drawn by
hash among its cluster's earlier records, so a chain has expected logarithmic length and a task makes its
codes without shuffle or state.
"""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition, SimpleDataSourceStreamReader

from .codes import table

# The characters codes are made of, by class.
CHARSET = ("0123456789", "abcdefghijklmnopqrstuvwxyz", "-_/.+#")
ALL = "".join(CHARSET)
#: Shares of variations: deletion, another character of the class, the rest any other class.
DELETE, ALIKE = 0.20, 0.64
DEFAULTS = {"N": 5000, "l": 20, "CN": 50, "sigma": 0.05, "seed": 42}
_M = (1 << 64) - 1


def _mix(*xs: int) -> int:
    """A 64-bit hash of whole numbers (multiply and shift)."""
    h = 0x9E3779B97F4A7C15
    for x in xs:
        h = (h ^ (x & _M)) * 0xBF58476D1CE4E5B9 & _M
        h ^= h >> 27
        h = h * 0x94D049BB133111EB & _M
        h ^= h >> 31
    return h


def _share(*xs: int) -> float:
    return _mix(*xs) / 2.0**64


def seed_code(cluster: int, length: int, seed: int) -> str:
    return "".join(ALL[_mix(seed, 1, cluster, k) % len(ALL)] for k in range(length))


def varied(code: str, record: int, sigma: float, seed: int) -> str:
    out = []
    for k, ch in enumerate(code):
        if _share(seed, 2, record, k) >= sigma:
            out.append(ch)
            continue
        u, pick = _share(seed, 3, record, k), _mix(seed, 4, record, k)
        own = next(c for c in CHARSET if ch in c)
        if u < DELETE:
            continue
        others = [c for c in own if c != ch] if u < DELETE + ALIKE else [c for c in ALL if c not in own]
        out.append(others[pick % len(others)])
    return "".join(out)


def cluster_of(record: int, clusters: int, seed: int) -> int:
    return _mix(seed, 5, record) % clusters


def parent_of(record: int, clusters: int, seed: int) -> int | None:
    """An earlier record of the same cluster, or None for the cluster's seed.

    Draws below the record are tried until one falls in the cluster; the chance to stop at the seed is that
    of drawing it among itself and the cluster's expected number of earlier records.
    """
    own = cluster_of(record, clusters, seed)
    if _share(seed, 6, record) < 1 / (1 + record / clusters):
        return None
    for turn in range(64 * clusters):
        at = _mix(seed, 7, record, turn) % record
        if cluster_of(at, clusters, seed) == own:
            return at
    return None


def code_of(record: int, length: int, clusters: int, sigma: float, seed: int) -> tuple[int, str]:
    chain, at = [], record
    while at is not None:
        chain.append(at)
        at = parent_of(at, clusters, seed) if at else None
    own = cluster_of(record, clusters, seed)
    code = seed_code(own, length, seed)
    for r in reversed(chain):
        code = varied(code, r, sigma, seed) or code  # a code is never varied away
    return own, code


def coded_strings(spark: SparkSession, N: int = 5000, l: int = 20, CN: int = 50, sigma: float = 0.05, seed: int = 42, sf_dir: str | None = None) -> DataFrame:  # noqa: E741
    """(rec_id, cluster, code), made where the rows are; no shuffle.

    sf_dir: the records are those of the orders there, by the remainder of their keys by N, instead of 0 to N - 1.
    """

    def make(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for pdf in batches:
            got = [code_of(int(k), l, CN, sigma, seed) for k in pdf["id"]]
            yield pd.DataFrame({"rec_id": pdf["id"], "cluster": [c for c, _ in got], "code": [s for _, s in got]})

    records = spark.range(N) if sf_dir is None else table(spark, sf_dir, "orders").where("o_orderkey is not null").select(F.pmod("o_orderkey", F.lit(N)).alias("id")).distinct()
    return records.mapInPandas(make, "rec_id long, cluster int, code string")


class _Slice(InputPartition):
    def __init__(self, lo: int, hi: int):
        self.lo, self.hi = lo, hi


class _Reader(DataSourceReader):
    def __init__(self, options: dict):
        self.n, self.length, self.clusters = int(options.get("n", DEFAULTS["N"])), int(options.get("l", DEFAULTS["l"])), int(options.get("cn", DEFAULTS["CN"]))
        self.sigma, self.seed, self.parts = float(options.get("sigma", DEFAULTS["sigma"])), int(options.get("seed", DEFAULTS["seed"])), int(options.get("partitions", 8))

    def partitions(self) -> list[InputPartition]:
        step = -(-self.n // self.parts)
        return [_Slice(k, min(k + step, self.n)) for k in range(0, self.n, step)]

    def read(self, partition: InputPartition) -> Iterator[tuple]:
        for k in range(partition.lo, partition.hi):
            yield (k, *code_of(k, self.length, self.clusters, self.sigma, self.seed))


class _Stream(SimpleDataSourceStreamReader):
    """The same records in order, so many per batch; offsets are record numbers, so a batch can be made again."""

    def __init__(self, options: dict):
        self.made, self.step = _Reader(options), int(options.get("rowsPerBatch", 100))

    def initialOffset(self) -> dict:
        return {"at": 0}

    def read(self, start: dict) -> tuple[Iterator[tuple], dict]:
        end = {"at": min(start["at"] + self.step, self.made.n)}
        return self.readBetweenOffsets(start, end), end

    def readBetweenOffsets(self, start: dict, end: dict) -> Iterator[tuple]:
        return iter(list(self.made.read(_Slice(start["at"], end["at"]))))  # Spark copies the iterator


class CodedStrings(DataSource):
    """spark.read.format('coded_strings').option('N', ...).load()"""

    @classmethod
    def name(cls) -> str:
        return "coded_strings"

    def schema(self) -> str:
        return "rec_id long, cluster int, code string"

    def reader(self, schema) -> DataSourceReader:
        return _Reader(self.options)

    def simpleStreamReader(self, schema) -> SimpleDataSourceStreamReader:
        return _Stream(self.options)


def register(spark: SparkSession) -> None:
    spark.dataSource.register(CodedStrings)
