"""Helpers that every operator of this subpackage shares: tables, word hashes, 64-bit mixing."""

from __future__ import annotations

import ctypes

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators.store import checkpointed, dropped, freed, shared_folder, written

__all__ = ["WordHashes", "checkpointed", "crc_mod", "dropped", "freed", "given_back", "mix64", "rolled", "rolled_all", "shared_folder", "table", "written"]

ROWS_PER_BATCH = 1000
MASK = (1 << 64) - 1


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """One input table; Arrow batches are kept small because a single text may be very long."""
    if int(spark.conf.get("spark.sql.execution.arrow.maxRecordsPerBatch")) > ROWS_PER_BATCH:
        spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", ROWS_PER_BATCH)
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def mix64(x: np.ndarray) -> np.ndarray:
    """A bijective avalanche of 64-bit values (vectorised)."""
    x = x.astype(np.uint64, copy=True)
    x ^= x >> np.uint64(30)
    x *= np.uint64(0xBF58476D1CE4E5B9)
    x ^= x >> np.uint64(27)
    x *= np.uint64(0x94D049BB133111EB)
    x ^= x >> np.uint64(31)
    return x


def given_back() -> None:
    """Returns a Python worker's free memory to the system, as idle workers stay beside those of later steps."""
    pa.default_memory_pool().release_unused()
    if trim := getattr(ctypes.CDLL(None), "malloc_trim", None):
        trim(0)


class WordHashes(dict):
    """64-bit hashes of words (str or bytes), remembered up to a bound and then forgotten."""

    def __init__(self, bound: int = 100_000) -> None:
        super().__init__()
        self.bound = bound

    def __missing__(self, word):
        value = xxhash.xxh64_intdigest(word)
        if len(self) >= self.bound:
            self.clear()
        self[word] = value
        return value

    def array(self, words: list) -> np.ndarray:
        return np.fromiter(map(self.__getitem__, words), np.uint64, len(words))


def rolled(ids: np.ndarray, width: int) -> np.ndarray:
    """A 64-bit hash of every run of ``width`` consecutive ids (none if there are fewer)."""
    n = len(ids) - width + 1
    if n <= 0:
        return np.empty(0, np.uint64)
    mixed, out = mix64(ids), np.zeros(n, np.uint64)
    for k in range(width):
        out *= np.uint64(0x9E3779B97F4A7C15)
        out += mixed[k : k + n]
    return mix64(out)


def rolled_all(ids: np.ndarray, widths: list[int]) -> dict[int, np.ndarray]:
    """``rolled`` for several widths: a run's sum goes on from that of the run one shorter, so all cost about as much as the widest."""
    mixed, sums, out = mix64(ids), np.zeros(len(ids), np.uint64), {}
    for width in range(1, max(widths, default=0) + 1):
        n = len(ids) - width + 1
        if n <= 0:
            break
        sums = sums[:n] * np.uint64(0x9E3779B97F4A7C15) + mixed[width - 1 :]
        if width in widths:
            out[width] = mix64(sums)
    return out


def crc_mod(col, modulus: int):
    """crc32 of the decimal text of an id, modulo a small number: how labelled rows are split in folds."""
    return F.pmod(F.crc32(col.cast("string").cast("binary")), F.lit(modulus))
