"""Helpers shared by the training-data operators: vectorised tokenising and hashing over Arrow buffers."""

from __future__ import annotations

import ctypes
import functools
import os
import tempfile
import uuid

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: Fixed values of the word rules: blanks are U+0020 and U+0009 to U+000D.
BLANK_SPLIT = r"[\x20\x09-\x0D]+"
#: After lower-casing A-Z, a word is made of digits, a-z and every character from U+0080 on.
TERM_SPLIT = r"[\x00-\x2F\x3A-\x60\x7B-\x7F]+"

UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"

_IS_BLANK = np.zeros(256, bool)
_IS_BLANK[[32, *range(9, 14)]] = True
#: Bytes to bytes: A-Z to a-z, everything that is no term byte to a blank.
TERM_BYTES = bytes(
    (b + 32) if 65 <= b <= 90 else b if (48 <= b <= 57 or 97 <= b <= 122 or b >= 128) else 32 for b in range(256)
)

_M1, _M2, _M3 = (np.uint64(x) for x in (0x9E3779B97F4A7C15, 0xBF58476D1CE4E5B9, 0x94D049BB133111EB))
_BYTE = np.random.default_rng(20240229).integers(1, 2**63, 256, dtype=np.uint64) * np.uint64(2) + np.uint64(1)
_BYTE[_IS_BLANK] = 0


def read(spark: SparkSession, sf_dir: str, table: str) -> DataFrame:
    """A table of the data directory; the path may be in any store that Spark reads."""
    return spark.read.parquet(f"{sf_dir}/{table}.parquet")


def ensure_checkpoint_dir(spark: SparkSession) -> str:
    """The shared folder for cut lineage and working tables: the session's. Only where none is set and Spark runs on this
    machine alone, one of our own; several machines would not see each other's files there."""
    path = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getConf().get("spark.checkpoint.dir")
    held = spark.sparkContext._jsc.sc().getCheckpointDir()
    if not path and not held.isEmpty():
        path = held.get()
    if not path:
        if not spark.sparkContext.master.startswith("local["):
            raise ValueError("set spark.checkpoint.dir to a folder that the driver and all executors share")
        path = "file://" + os.path.join(tempfile.gettempdir(), "graphstitch-checkpoints")
    if held.isEmpty():
        spark.sparkContext.setCheckpointDir(path)
    return path


def cut(df: DataFrame) -> DataFrame:
    """Materialised as a table in the shared folder, which survives lost executors. Unlike a checkpoint it brings along no
    constraints of the plan before, which double with each round of a loop, and its size is known to the planner."""
    path = f"{ensure_checkpoint_dir(df.sparkSession).rstrip('/')}/cut-{uuid.uuid4().hex}"
    df.write.parquet(path)
    out = df.sparkSession.read.schema(df.schema).parquet(path)
    out._cut_path = path
    return out


def forget(*tables: DataFrame) -> None:
    """Deletes tables that cut() made and that nothing will read again."""
    for t in tables:
        jvm, session = t.sparkSession._jvm, t.sparkSession._jsparkSession
        path = jvm.org.apache.hadoop.fs.Path(t._cut_path)
        path.getFileSystem(session.sessionState().newHadoopConf()).delete(path, True)


#: Rows of a few numbers each that may be broadcast.
BROADCAST_ROWS = 200_000


def small(df: DataFrame, most: int | None = None) -> DataFrame:
    """A materialised table of narrow rows, marked for broadcast only where its counted rows are within the bound; beyond, it is
    joined by an exchange."""
    return F.broadcast(df) if df.count() <= (BROADCAST_ROWS if most is None else most) else df


def without(text, chars: str, by: str = ""):
    """Native: each of a few ASCII characters replaced; plain byte searches, far cheaper than translate or a regex."""
    for c in chars:
        text = F.replace(text, F.lit(c), F.lit(by))
    return text


def blank_words(text):
    """Native: the words of a text column, blanks as above; null gives none."""
    return F.array_remove(F.split(without(F.coalesce(text, F.lit("")), "\t\n\x0b\x0c\r", " "), " "), "")


def term_text(text):
    """Native: A-Z lower-cased and nothing else. lower() does just that unless a non-ASCII capital occurs."""
    text = F.coalesce(text, F.lit(""))
    return F.when(text.rlike(r"[\p{IsUppercase}\p{Lt}&&[^\x00-\x7F]]"), F.translate(text, UPPER, LOWER)).otherwise(F.lower(text))


def term_words(text):
    """Native: lower-cased words of digits, a-z and non-ASCII characters."""
    return F.array_remove(F.split(term_text(text), TERM_SPLIT), "")


def mix(x: np.ndarray) -> np.ndarray:
    """A 64-bit finaliser."""
    with np.errstate(over="ignore"):
        x = (x ^ (x >> np.uint64(30))) * _M2
        x = (x ^ (x >> np.uint64(27))) * _M3
        return x ^ (x >> np.uint64(31))


def pair(a: np.ndarray, b: np.ndarray, salt: int = 0) -> np.ndarray:
    """An order-sensitive 64-bit name of two names."""
    with np.errstate(over="ignore"):
        return mix(a * _M1 + (b ^ (b >> np.uint64(32))) * _M3 + np.uint64(salt * 0x632BE59BD9B4E019 % 2**64))


def grams(x: np.ndarray, k: int) -> np.ndarray:
    """Names of all k consecutive items, by doubling; length len(x) - k + 1."""
    if len(x) < k:
        return np.empty(0, np.uint64)
    out, span, power, width = None, 0, x, 1
    while True:
        if k & width:
            if out is None:
                out, span = power, width
            else:
                n = len(x) - span - width + 1
                out, span = pair(out[:n], power[span : span + n], width), span + width
        if 2 * width > k:
            return out
        n = len(power) - width
        power, width = pair(power[:n], power[width : width + n], width), 2 * width


def text_buffer(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """Bytes and offsets of a string column (nulls are empty), without copying where Arrow allows."""
    if column.null_count:
        column = column.fill_null("")
    if not pa.types.is_large_string(column.type):
        column = column.cast(pa.large_string())
    _, offsets, data = column.buffers()
    offs = np.frombuffer(offsets, np.int64)[column.offset : column.offset + len(column) + 1]
    raw = np.frombuffer(data, np.uint8)[offs[0] : offs[-1]] if data is not None and len(offs) and offs[-1] > offs[0] else np.empty(0, np.uint8)
    return raw, offs - offs[0]


def slices(column: pa.Array, most: int = 4 << 20):
    """Row ranges whose texts hold about `most` bytes (one text may hold more)."""
    _, offs = text_buffer(column)
    at = 0
    while at < len(column):
        to = max(at + 1, int(np.searchsorted(offs, offs[at] + most, "right")) - 1)
        yield at, min(to, len(column))
        at = to


def spans(data: np.ndarray, offs: np.ndarray, blank: np.ndarray = _IS_BLANK) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Starts and ends of the words, and for each text the index of its first word (one more at the end)."""
    solid = ~blank[data]
    first, last = solid.copy(), solid.copy()
    if len(data):
        first[1:] &= ~solid[:-1]
        last[:-1] &= ~solid[1:]
        edge = offs[(offs > 0) & (offs < len(data))]
        first[edge] = solid[edge]
        last[edge - 1] = solid[edge - 1]
    starts = np.flatnonzero(first)
    return starts, np.flatnonzero(last) + 1, np.searchsorted(starts, offs)


@functools.lru_cache(1)
def _powers(n: int) -> np.ndarray:
    out = np.full(n, _M1 | np.uint64(1), np.uint64)
    out[0] = 1
    with np.errstate(over="ignore"):
        return np.cumprod(out)


def word_names(data: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
    """A 64-bit name of each word; equal words have equal names in every task."""
    if not len(starts):
        return np.empty(0, np.uint64)
    body = data[starts[0] :]
    begin = starts - starts[0]
    length = np.diff(np.append(begin, len(body)))
    powers = _powers(1 << int(max(64, length.max()) - 1).bit_length())
    within = np.arange(len(body)) - np.repeat(begin, length)
    with np.errstate(over="ignore"):
        total = np.add.reduceat(_BYTE[body] * powers[within], begin)
        return mix(total + (ends - starts).astype(np.uint64) * _M2)


def lists_of(lengths: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """For groups of these lengths laid end to end: the group of each item, and its place in it."""
    group = np.repeat(np.arange(len(lengths)), lengths)
    return group, np.arange(len(group)) - np.repeat(np.cumsum(lengths) - lengths, lengths)


def tidy(function):
    """A function over batches that hands freed memory back to the system at its end: workers are kept for later tasks, and
    what their allocators hold meanwhile counts against the executor."""

    @functools.wraps(function)
    def run(batches):
        try:
            yield from function(batches)
        finally:
            pa.default_memory_pool().release_unused()
            trim = getattr(ctypes.CDLL(None), "malloc_trim", None)
            if trim:
                trim(0)

    return run


class Memo:
    """A bounded memory of a function over many keys: what was not used for a whole generation is forgotten."""

    def __init__(self, fill, most: int = 250_000):
        self.fill, self.most, self.young, self.old = fill, most, {}, {}

    def many(self, keys: list) -> list:
        got = list(map(self.young.get, keys))
        if None not in got:
            return got
        missing = list({k for k, v in zip(keys, got) if v is None})
        found = {k: self.old[k] for k in missing if k in self.old}
        missing = [k for k in missing if k not in found]
        found.update(zip(missing, self.fill(missing)))
        if len(self.young) + len(found) > self.most:
            self.old, self.young = self.young, {}
        self.young.update(found)
        return [found[k] if v is None else v for k, v in zip(keys, got)]
