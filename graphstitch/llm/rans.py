"""Token ids in a binary format coded with a static range asymmetric numeral system.

One frequency table, counted over all ids, serves the whole corpus. A block holds whole documents (about `BLOCK_IDS` ids) and
is coded on its own by `LANES` interleaved coders: lane l has the ids l, l + LANES, ...; states are 64-bit, they give off 32
bits at a time, and all lanes step together. Every `CHECK_STEPS` steps a checkpoint keeps the lanes' states and the place in
the stream, so parts of a block can be decoded in parallel too. A CRC-32 over the ids guards each block.

Block, little-endian: "GSRA", version u8, table bits u8, lanes u16, table's crc u32, documents u32, ids u32, crc of the ids
u32, checkpoints u32, words u32; then per document its id i64, whether it has one u8, and its count of ids u32; then per
checkpoint its place in the stream u32 and the states u64 (the first checkpoint is the start); then the words u32.

The file is a Parquet table of blocks in ascending doc_id order: part, number in the part, first id in the part, block.

Defined results: null and empty texts have only the end id; rows without doc_id come first; repeated doc_ids keep all their
rows, in the order of their ids; an empty table gives an empty file and result; other columns are ignored.
"""

from __future__ import annotations

import functools
import json
import os
import re
import struct
import uuid
import zlib

import numpy as np
import public_tokenizers
import pyarrow as pa
import pyarrow.compute as pc
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from graphstitch.llm.common import ensure_checkpoint_dir, slices, text_buffer

TOKENIZER, END_ID = "word_bpe_49k.json", 1
BITS, LANES, CHECK_STEPS, BLOCK_IDS = 20, 1024, 128, 1 << 18
#: Bytes of text that are cut at once.
SLICE = 8 << 20
#: Parts whose totals may be broadcast.
PARTS_BROADCAST = 1_000_000
#: The settings of the tokenizer file for which pre-tokens are cut here; with any others the library does it all.
NORMALIZER = {"type": "Sequence", "normalizers": [{"type": "NFC"}, {"type": "Replace", "pattern": {"Regex": "\\s+"}, "content": " "}, {"type": "Lowercase"}]}
PRE_TOKENIZER = {
    "type": "Sequence",
    "pretokenizers": [
        {"type": "Split", "pattern": {"Regex": "'s|'t|'re|'ve|'m|'ll|'d|[\\p{L}]+|[\\p{N}]|[^\\s\\p{L}\\p{N}]+"}, "behavior": "Removed", "invert": True},
        {"type": "ByteLevel", "add_prefix_space": False, "trim_offsets": True, "use_regex": False},
    ],
}
_LOW, _HEAD = np.uint64(1 << 31), struct.Struct("<4sBBHIIIIII")
_BLOCKS = "part int, number int, at long, ids long, block binary"


#: Kinds of bytes in lower-cased text of characters below U+0100, as the tokenizer's own pattern has them, for one
#: byte and for the second of C2 and C3. A run left to the library whole is of one kind.
_WHITE, _LETTER, _DIGIT, _OTHER, _WHOLE = range(5)


def _kind_of(c: int) -> int:
    if c in (*range(9, 14), 32, 0x85, 0xA0):
        return _WHITE
    if 97 <= c <= 122 or c in (0xAA, 0xB5, 0xBA) or (c >= 0xDF and c != 0xF7):
        return _LETTER
    return _DIGIT if 48 <= c <= 57 or c in (0xB2, 0xB3, 0xB9, 0xBC, 0xBD, 0xBE) else _OTHER


_KINDS = bytes(_kind_of(b + 32 if 65 <= b <= 90 else b) if b < 128 else _OTHER for b in range(256))
_LOWER = bytes(b + 32 if 65 <= b <= 90 else b for b in range(256))
#: By the code point less 128; capitals from U+00C0 on are letters too.
_HIGH_KINDS = np.array([_LETTER if 0xC0 <= c <= 0xDE and c != 0xD7 else _kind_of(c) for c in range(128, 256)], np.uint8)


def gather(flat: np.ndarray, starts: np.ndarray, sizes: np.ndarray) -> np.ndarray:
    """The pieces of these places and sizes, end to end."""
    ends = np.cumsum(sizes)
    return flat[np.repeat(starts - (ends - sizes), sizes) + np.arange(int(ends[-1]) if len(ends) else 0)]


class Tokens:
    """Ids of texts as 16-bit numbers where the vocabulary allows, else 32-bit ones. White space separates pre-tokens, so the
    runs between plain blanks and line ends encode on their own. Runs of characters below U+0100 are lower-cased and cut into
    pre-tokens here, all texts of a batch at once; other runs, and those with special tokens, stay whole. Arrow's dictionary
    tells which of them were met before, and their ids are remembered; unknown pre-tokens go to the library's model together,
    and come back apart by the mark that ends each of them, unknown whole runs to the library as it is."""

    def __init__(self, path: str, most: int = 300_000, longest: int = 64):
        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        from tokenizers import Tokenizer, pre_tokenizers

        self.tokenizer = Tokenizer.from_file(path)
        self.kind = np.dtype("<u2" if self.tokenizer.get_vocab_size() <= 1 << 16 else "<u4")
        vocabulary = self.tokenizer.get_vocab()
        self.ends = np.zeros(max(vocabulary.values()) + 1, bool)
        self.ends[[i for t, i in vocabulary.items() if t.endswith("</w>")]] = True
        with open(path, encoding="utf-8") as f:
            form = json.load(f)
        self.specials = [t["content"].encode() for t in form["added_tokens"]]
        # a special token of one kind of characters could not be told from a pre-token, one with a blank not be found in a run
        mixed = all(len(set(t.translate(_KINDS)) - {_WHITE}) > 1 and not set(t) & {10, 32} and t.isascii() for t in self.specials)
        self.known = mixed and form["pre_tokenizer"] == PRE_TOKENIZER and form["normalizer"] == NORMALIZER and form["model"].get("end_of_word_suffix") == "</w>"
        # pre-tokens are normalised and cut already; the library's byte letters are put in here, so that only its model is left to run
        self.model = Tokenizer.from_str(json.dumps(form | {"normalizer": None, "pre_tokenizer": {"type": "WhitespaceSplit"}, "added_tokens": []})) if self.known else None
        letters = pre_tokenizers.ByteLevel(add_prefix_space=False, use_regex=False)
        self.letters = {i: letters.pre_tokenize_str(chr(i))[0][0] for i in range(256) if i != 32}
        # what is remembered: keys of up to `longest` bytes with the places and sizes of their ids, and how often each was used
        self.most, self.longest = most, longest
        self.keys, self.ids = pa.array([], pa.binary()), np.empty(0, self.kind)
        self.sizes = self.uses = np.empty(0, np.int64)

    def _library(self, texts: list[str]) -> tuple[np.ndarray, np.ndarray]:
        got = [e.ids for e in self.tokenizer.encode_batch_fast(texts, add_special_tokens=False)] if texts else []
        return np.array([i for ids in got for i in ids], self.kind), np.array([len(ids) for ids in got], np.int64)

    def _model(self, pieces: list[str]) -> tuple[np.ndarray, np.ndarray]:
        """All at once, with blanks between; the last token of each has the mark of a word's end."""
        ids = np.array(self.model.encode_batch_fast([" ".join(pieces).translate(self.letters)], add_special_tokens=False)[0].ids, np.int64)
        cuts = np.flatnonzero(self.ends[ids]) + 1
        if len(cuts) != len(pieces):
            return self._library(pieces)
        return ids.astype(self.kind), np.diff(cuts, prepend=0)

    def _fill(self, keys: list[str], odd: bool) -> tuple[np.ndarray, np.ndarray]:
        """Ids of the keys, end to end, and their sizes."""
        if not odd:
            return self._model(keys)
        specials = [t.decode() for t in self.specials]
        whole = np.array([max(k) >= "\u0100" or any(t in k for t in specials) for k in keys], bool)
        back = np.argsort(np.argsort(whole, kind="stable"))
        parts = self._model([k for k, w in zip(keys, whole) if not w]), self._library([k for k, w in zip(keys, whole) if w])
        ids, sizes = (np.concatenate(x) for x in zip(*parts))
        return gather(ids, (np.cumsum(sizes) - sizes)[back], sizes[back]), sizes[back]

    def cut(self, data: np.ndarray, offs: np.ndarray) -> tuple[pa.Array, np.ndarray, bool]:
        """Pre-tokens and whole runs of texts laid end to end, the index of each text's first (one more at the end), and whether
        there are whole runs."""
        n, raw = len(data), data.tobytes()
        low, kinds = (np.frombuffer(bytearray(raw.translate(t)), np.uint8) for t in (_LOWER, _KINDS))
        edge = offs[offs < n]
        high = np.flatnonzero(data >= 0xC0)
        lead = high[data[high] < 0xC4]
        second = data[lead + 1]
        kinds[lead] = kinds[lead + 1] = kind = _HIGH_KINDS[(data[lead] - 0xC2) * np.uint8(64) + (second - 0x80)]
        low[lead[(data[lead] == 0xC3) & (second <= 0x9E) & (second != 0x97)] + 1] += 0x20
        odd = [high[data[high] >= 0xC4]]
        for special in self.specials:
            if special in raw:
                at = np.array([m.start() for m in re.finditer(b"(?=" + re.escape(special) + b")", raw)])
                odd.append(at[offs[np.searchsorted(offs, at, "right")] >= at + len(special)])  # not across two texts
        odd = np.concatenate(odd)
        if len(odd):
            gap, begin, marked = (data == 32) | (data == 10), np.zeros(n, bool), np.zeros(n, bool)
            begin[1:] = gap[:-1]
            begin[edge] = marked[odd] = True
            begins = np.flatnonzero(begin)
            inside = np.repeat(np.logical_or.reduceat(marked, begins), np.diff(begins, append=n)) & ~gap
            low[inside], kinds[inside] = data[inside], _WHOLE
        first = kinds == _DIGIT
        first[lead[kind == _DIGIT] + 1] = False
        first[1:] |= kinds[1:] != kinds[:-1]
        first[edge] = True
        solid = kinds != _WHITE
        first &= solid
        ticks = np.flatnonzero(low[:-1] == 39)
        ticks = ticks[first[ticks] & (kinds[ticks] == _OTHER) & (kinds[ticks + 1] == _LETTER)]
        if len(ticks):  # 's and the like: an apostrophe that begins, with its letters
            opens = np.zeros(n + 2, bool)
            opens[edge] = True
            tail = np.append(low, [0, 0]).astype(np.int64)
            b, c = tail[ticks + 1], tail[ticks + 2]
            short = np.isin(b, list(b"stmd"))
            long = np.isin(b << 8 | c, [int.from_bytes(x, "big") for x in (b"re", b"ve", b"ll")]) & ~opens[ticks + 2]
            found = (short | long) & ~opens[ticks + 1]
            ticks, size = ticks[found], np.where(short, 2, 3)[found]
            first[ticks + 1] = False
            after = ticks + size
            after = after[after < n]
            first[after] |= kinds[after] == _LETTER
        body, begins = low[solid], np.flatnonzero(first[solid])
        pieces = pa.Array.from_buffers(pa.binary(), len(begins), [None, pa.py_buffer(np.append(begins, len(body)).astype(np.int32)), pa.py_buffer(body)])
        return pieces, np.searchsorted(np.flatnonzero(first), offs), bool(len(odd))

    def encode(self, column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
        """Ids of the texts of a string column, end to end, and the place of each text's first (one more at the end)."""
        if not self.known:
            ids, sizes = self._library(column.fill_null("").to_pylist())
            return ids, np.concatenate([[0], np.cumsum(sizes)])
        column.validate(full=True)
        pieces, firsts, odd = self.cut(*text_buffer(column))
        if not len(pieces):
            return np.empty(0, self.kind), np.zeros(len(column) + 1, np.int64)
        old = len(self.keys)
        both = pa.chunked_array([self.keys, pieces]).dictionary_encode()
        keys = both.chunk(both.num_chunks - 1).dictionary
        codes = both.chunk(both.num_chunks - 1).indices.to_numpy()
        ids, sizes = self._fill([k.decode() for k in keys[old:].to_pylist()], odd)
        self.keys, self.ids, self.sizes = keys, np.concatenate([self.ids, ids]), np.concatenate([self.sizes, sizes])
        begins = np.cumsum(self.sizes) - self.sizes
        length = self.sizes[codes]
        out = gather(self.ids, begins[codes], length)
        places = np.concatenate([[0], np.cumsum(length)])[firsts]
        self.uses = np.append(self.uses, np.zeros(len(keys) - old, np.int64)) + np.bincount(codes, minlength=len(keys))
        self._forget(begins)
        return out, places

    def _forget(self, begins: np.ndarray) -> None:
        """Drops long new keys, and where there are too many keys the less used half."""
        keep = np.flatnonzero(pc.binary_length(self.keys).to_numpy() <= self.longest)
        if len(keep) > self.most:
            keep = np.sort(keep[np.argsort(-self.uses[keep], kind="stable")[: self.most // 2]])
            self.uses //= 2
        if len(keep) < len(self.keys):
            self.keys, self.ids = self.keys.take(pa.array(keep)), gather(self.ids, begins[keep], self.sizes[keep])
            self.sizes, self.uses = self.sizes[keep], self.uses[keep]

    def batch(self, texts: list[str | None]) -> list[bytes]:
        ids, places = self.encode(pa.array(texts, pa.large_string()))
        return [ids[x:y].tobytes() for x, y in zip(places[:-1], places[1:])]

    def __call__(self, text: str | None) -> bytes:
        return self.batch([text])[0]


@functools.lru_cache(2)
def tokens(path: str) -> Tokens:
    return Tokens(path)


class Table:
    """Frequencies that sum to 2**bits; every id that was counted has one at least."""

    def __init__(self, counts: np.ndarray, bits: int = BITS):
        total = int(counts.sum())
        freq = np.where(counts > 0, np.maximum(1, counts * (1 << bits) // max(total, 1)), 0).astype(np.int64)
        if not total:
            freq[0] = 1 << bits
        left = (1 << bits) - int(freq.sum())
        while left:  # the most frequent ids give or take the rest
            order = np.argsort(-freq, kind="stable")[: max(1, min(abs(left), int((freq > 1).sum())))]
            step = np.sign(left) if abs(left) <= len(order) else left // len(order) if left > 0 else -1
            freq[order[: abs(left)] if abs(left) < len(order) else order] += step
            left = (1 << bits) - int(freq.sum())
        self.bits, self.freq = bits, freq.astype(np.uint64)
        self.start = np.concatenate([[0], np.cumsum(self.freq)[:-1]]).astype(np.uint64)
        self.crc = zlib.crc32(freq.astype("<u4").tobytes())

    @functools.cached_property
    def slots(self) -> np.ndarray:
        return np.repeat(np.arange(len(self.freq), dtype=np.uint32), self.freq.astype(np.int64))


def encode_block(ids: np.ndarray, docs: list[int | None], sizes: np.ndarray, table: Table, lanes: int = LANES, every: int = CHECK_STEPS) -> bytes:
    steps = -(-len(ids) // lanes)
    padded = np.full(steps * lanes, int(np.argmax(table.freq)), np.int64)
    padded[: len(ids)] = ids
    grid, bits = padded.reshape(steps, lanes), np.uint64(table.bits)
    state = np.full(lanes, _LOW, np.uint64)
    words: list[np.ndarray] = []
    checks, given = [], 0
    for t in range(steps - 1, -1, -1):
        f, c = table.freq[grid[t]], table.start[grid[t]]
        if not f.all():
            raise ValueError("an id is not in the frequency table")
        full = state >= ((_LOW >> bits) << np.uint64(32)) * f
        words.append((state[full] & np.uint64(0xFFFFFFFF)).astype("<u4"))
        given += len(words[-1])
        state = np.where(full, state >> np.uint64(32), state)
        q = state // f
        state = (q << bits) + (state - q * f) + c
        if t % every == 0:
            checks.append((given, state))
    stream = np.concatenate(words[::-1]) if words else np.empty(0, "<u4")
    head = _HEAD.pack(b"GSRA", 1, table.bits, lanes, table.crc, len(docs), len(ids), zlib.crc32(ids.astype("<u4").tobytes()), len(checks), len(stream))
    known = np.array([d is not None for d in docs], np.uint8)
    body = [head, np.array([d or 0 for d in docs], "<i8").tobytes(), known.tobytes(), np.asarray(sizes, "<u4").tobytes()]
    for before, s in reversed(checks):
        body += [struct.pack("<I", given - before), s.astype("<u8").tobytes()]
    return b"".join([*body, stream.tobytes()])


def decode_block(block: bytes, table: Table, first: int = 0, last: int | None = None) -> tuple[list[int | None], np.ndarray, np.ndarray]:
    """Documents, their counts, and the ids of the checkpoints' sections first to last (all of them by default)."""
    magic, version, bits, lanes, crc, n_docs, n_ids, ids_crc, n_checks, n_words = _HEAD.unpack_from(block)
    if magic != b"GSRA" or version != 1 or crc != table.crc or bits != table.bits:
        raise ValueError("not a block of this format and table")
    at = _HEAD.size
    doc = np.frombuffer(block, "<i8", n_docs, at)
    known = np.frombuffer(block, np.uint8, n_docs, at + 8 * n_docs)
    sizes = np.frombuffer(block, "<u4", n_docs, at + 9 * n_docs)
    at += 13 * n_docs
    places = [at + i * (4 + 8 * lanes) for i in range(n_checks)]
    stream = np.frombuffer(block, "<u4", n_words, at + n_checks * (4 + 8 * lanes)).astype(np.uint64)
    steps, every = -(-n_ids // lanes), CHECK_STEPS
    last = n_checks if last is None else last
    out = []
    if first < last:
        place = struct.unpack_from("<I", block, places[first])[0]
        state = np.frombuffer(block, "<u8", lanes, places[first] + 4).astype(np.uint64)
        mask, bits = np.uint64((1 << bits) - 1), np.uint64(bits)
        for _ in range(first * every, min(last * every, steps)):
            slot = state & mask
            s = table.slots[slot.astype(np.int64)]
            state = table.freq[s] * (state >> bits) + slot - table.start[s]
            out.append(s)
            low = np.flatnonzero(state < _LOW)
            state[low] = (state[low] << np.uint64(32)) | stream[place : place + len(low)]
            place += len(low)
    ids = (np.concatenate(out) if out else np.empty(0, np.uint32))[: n_ids - first * every * lanes]
    if first == 0 and last == n_checks and zlib.crc32(ids.astype("<u4").tobytes()) != ids_crc:
        raise ValueError("the ids of a block do not match its checksum")
    return [int(d) if k else None for d, k in zip(doc, known)], sizes, ids


def tokenised(docs: DataFrame, path: str, end_id: int = END_ID) -> DataFrame:
    """doc_id and the ids of the text, with the end id behind, as bytes."""

    def run(batches):
        encode = tokens(path)
        width = encode.kind.itemsize
        for batch in (b.slice(x, y - x) for b in batches for x, y in slices(b.column("text"), SLICE)):
            ids, places = encode.encode(batch.column("text"))
            bounds = places + np.arange(len(places))
            out, mine = np.full(len(ids) + len(batch), end_id, encode.kind), np.ones(len(ids) + len(batch), bool)
            mine[bounds[1:] - 1] = False
            out[mine] = ids
            column = pa.Array.from_buffers(pa.binary(), len(batch), [None, pa.py_buffer((bounds * width).astype(np.int32)), pa.py_buffer(out)])
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), column], ["doc_id", "ids"])

    return docs.select("doc_id", "text").mapInArrow(run, "doc_id long, ids binary")


def count_ids(ids: DataFrame, kind: np.dtype) -> np.ndarray:
    """Occurrences of each id over all documents; each task sends a row per id it met."""

    def run(batches):
        total = np.zeros(1 << 16, np.int64)
        for batch in batches:
            got = np.bincount(np.frombuffer(b"".join(batch.column("ids").to_pylist()), kind))
            if len(got) > len(total):
                total = np.pad(total, (0, len(got) - len(total)))
            total[: len(got)] += got
        met = np.flatnonzero(total)
        yield pa.RecordBatch.from_arrays([pa.array(met), pa.array(total[met])], ["id", "n"])

    rows = ids.select("ids").mapInArrow(run, "id long, n long").groupBy("id").agg(F.sum("n").alias("n")).collect()
    out = np.zeros(max([r["id"] for r in rows], default=0) + 1, np.int64)
    for r in rows:
        out[r["id"]] = r["n"]
    return out


def write_ids(docs: DataFrame, target: str, tokenizer: str | None = None, end_id: int = END_ID, block_ids: int = BLOCK_IDS) -> Table:
    """Writes the ids of all documents, each with the end id behind, in ascending doc_id order. The texts are tokenised once,
    to a table beside the target; it is counted, then ordered and coded."""
    path = tokenizer or public_tokenizers.path(TOKENIZER)
    kind, spark = tokens(path).kind, docs.sparkSession
    tokenised(docs, path, end_id).write.parquet(f"{target}-raw")
    raw = spark.read.schema("doc_id long, ids binary").parquet(f"{target}-raw")
    table = Table(count_ids(raw, kind))

    def run(batches):
        part = TaskContext.get().partitionId()
        held: list[bytes] = []
        names: list[int | None] = []
        number = at = size = 0

        def flush():
            ids = np.frombuffer(b"".join(held), kind)
            block = encode_block(ids, names, np.array([len(h) // kind.itemsize for h in held]), table)
            return pa.RecordBatch.from_arrays([pa.array([part], pa.int32()), pa.array([number], pa.int32()), pa.array([at], pa.int64()), pa.array([len(ids)], pa.int64()), pa.array([block], pa.binary())], ["part", "number", "at", "ids", "block"])

        for batch in batches:
            for doc, ids in zip(batch.column("doc_id").to_pylist(), batch.column("ids").to_pylist()):
                held.append(ids)
                names.append(doc)
                size += len(ids) // kind.itemsize
                if size >= block_ids:
                    yield flush()
                    number, at, size = number + 1, at + size, 0
                    held.clear()
                    names.clear()
        if held:
            yield flush()

    ordered = raw.repartitionByRange(F.col("doc_id").asc_nulls_first()).sortWithinPartitions(F.col("doc_id").asc_nulls_first(), "ids")
    ordered.mapInArrow(run, _BLOCKS).write.parquet(target)
    return table


def read_ids(spark: SparkSession, target: str, table: Table) -> DataFrame:
    """Per document of the file: doc_id, start, n_tokens, ids_crc32."""

    def run(batches):
        for batch in batches:
            for begin, block in zip(batch.column("begin").to_pylist(), batch.column("block")):
                docs, sizes, ids = decode_block(block.as_py(), table)
                ends = np.cumsum(sizes.astype(np.int64))
                raw = ids.astype("<u4").tobytes()
                crc = [zlib.crc32(raw[4 * (e - n) : 4 * e]) for e, n in zip(ends.tolist(), sizes.tolist())]
                yield pa.RecordBatch.from_arrays([pa.array(docs, pa.int64()), pa.array(begin + ends - sizes), pa.array(sizes.astype(np.int64)), pa.array(crc, pa.int64())], ["doc_id", "start", "n_tokens", "ids_crc32"])

    blocks = spark.read.schema(_BLOCKS).parquet(target)
    totals = blocks.groupBy("part").agg(F.sum("ids").alias("total"))
    # a row per part of the file; the window over them holds numbers only
    before = F.sum("total").over(Window.orderBy("part")) - F.col("total")
    begins = totals.select("part", before.alias("before"))
    begins = F.broadcast(begins) if totals.count() <= PARTS_BROADCAST else begins
    placed = blocks.join(begins, "part").select((F.col("before") + F.col("at")).alias("begin"), "block")
    return placed.mapInArrow(run, "doc_id long, start long, n_tokens long, ids_crc32 long")


def round_trip(docs: DataFrame, tokenizer: str | None = None) -> DataFrame:
    spark = docs.sparkSession
    target = f"{ensure_checkpoint_dir(spark).rstrip('/')}/ids-{uuid.uuid4().hex}"
    return read_ids(spark, target, write_ids(docs, target, tokenizer))
