"""Helpers that the operators of this subpackage share."""

from __future__ import annotations

import contextlib
import uuid
import zlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: Unicode White_Space without the ASCII separators 1C-1F, which str.split() also cuts at.
ODD_SPACE = "\x1c\x1d\x1e\x1f"


def give_back() -> None:
    """Return freed memory to the system: workers live long and run one operator after another."""
    import ctypes

    with contextlib.suppress(OSError, AttributeError):
        ctypes.CDLL(None).malloc_trim(0)


def _lean_worker() -> None:
    """Have the C library, also below Arrow, give back arrays of over 256 KB as soon as they are freed."""
    import ctypes

    with contextlib.suppress(OSError, AttributeError):
        libc = ctypes.CDLL(None)
        libc.mallopt(-3, 256 << 10)  # M_MMAP_THRESHOLD
        libc.mallopt(-1, 8 << 20)  # M_TRIM_THRESHOLD
        pa.set_memory_pool(pa.system_memory_pool())


#: What operators keep in a worker between tasks, by operator.
HELD: dict[str, dict] = {}


def only(owner: str) -> None:
    """Drop what other operators keep in this worker; called where a task of an operator begins."""
    others = [held for name, held in HELD.items() if name != owner and held]
    for held in others:
        held.clear()
    if owner:  # the operators without a name share the powers
        _POWERS.clear()
    give_back()


_lean_worker()
#: Rows that go to a Python worker together: whole texts, so fewer than the usual 10,000.
BATCH_ROWS = 2000


def lean(spark: SparkSession) -> None:
    spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", str(BATCH_ROWS))


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_folder(spark: SparkSession, what: str) -> str:
    """A fresh folder below spark.checkpoint.dir, which driver and executors share.

    Only where the session names none (tests on one machine) is one chosen here.
    """
    base = spark.conf.get("spark.checkpoint.dir", None)
    if not base:
        held = spark.sparkContext._jsc.sc().getCheckpointDir()
        base = held.get() if held.isDefined() else "file:///tmp/checkpoints"
    return f"{base.rstrip('/')}/{what}-{uuid.uuid4().hex}"


def written(df: DataFrame, what: str) -> DataFrame:
    """df written to the shared folder and read back: lineage ends, any executor may go.

    Written tables of a session are removed when it is told to clean up, not here:
    the caller's lazily evaluated result may still read them.
    """
    path = shared_folder(df.sparkSession, what)
    df.write.option("compression", "zstd").parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def crc_mod(col, n: int):
    """crc32 of the id written as text, modulo n; null ids count as empty text."""
    return F.crc32(F.coalesce(col.cast("string"), F.lit("")).cast("binary")) % n


def crc_mod_py(value, n: int) -> int:
    return zlib.crc32(b"" if value is None else str(value).encode()) % n


MASK64 = np.uint64(0xFFFFFFFFFFFFFFFF)


def mix64(x: np.ndarray) -> np.ndarray:
    """Avalanche of 64-bit words (the well-known splitmix finaliser)."""
    x = x ^ (x >> np.uint64(30))  # a new array, which the rest changes in place
    x *= np.uint64(0xBF58476D1CE4E5B9)
    x ^= x >> np.uint64(27)
    x *= np.uint64(0x94D049BB133111EB)
    x ^= x >> np.uint64(31)
    return x


#: Odd multipliers of two independent polynomial hashes modulo 2**64.
BASES = (0x9E3779B97F4A7C15, 0xD6E8FEB86659FD93)
_POWERS: dict[int, tuple[np.ndarray, np.ndarray]] = {}


def powers(base: int, n: int) -> tuple[np.ndarray, np.ndarray]:
    """base**i and base**-i modulo 2**64 for i < n at least; kept between calls."""
    held = _POWERS.get(base)
    if held is None or len(held[0]) < n:
        size = max(1 << 16, 1 << int(n - 1).bit_length()) if n else 1 << 16
        inverse = pow(base, -1, 1 << 64)
        up, down = np.full(size, base, np.uint64), np.full(size, inverse, np.uint64)
        up[0] = down[0] = 1
        held = _POWERS[base] = (np.multiply.accumulate(up), np.multiply.accumulate(down))
    return held


def prefix_hash(codes: np.ndarray, base: int) -> np.ndarray:
    """P with P[i] = sum of codes[j] * base**j over j < i, modulo 2**64."""
    out = np.zeros(len(codes) + 1, np.uint64)
    up, _ = powers(base, len(codes) + 1)
    terms = codes.astype(np.uint64)
    terms += np.uint64(1)
    terms *= up[: len(codes)]
    np.cumsum(terms, out=out[1:])
    return out


def window_hash(prefix: np.ndarray, k: int, base: int) -> np.ndarray:
    """span_hash of every window of k codes, by where it starts: without looking places up one by one."""
    _, down = powers(base, len(prefix))
    x = prefix[k:] - prefix[:-k]
    x *= down[: len(x)]
    return mix64(x)


def span_hash(prefix: np.ndarray, start: np.ndarray, end: np.ndarray, base: int) -> np.ndarray:
    """Position-free hash of codes[start:end], mixed."""
    _, down = powers(base, len(prefix))
    return mix64((prefix[end] - prefix[start]) * down[start])
