"""Byte-level BPE by tree reduction.

Text level: a long text is halved; around the middle, the window between the nearest two sure places is encoded on its own,
and so are the parts before and behind it, which are halved again. A sure place is a single blank or line end between two
other characters: the pre-tokenising pattern never matches across it, so nothing outside can change. A leaf falls into chunks
at all its sure places. Piece level: every match of the pattern is halved as well, down to `LEAF_BYTES`; its halves' tokens are joined by
re-encoding a window of tokens around the seam, widened on the side that does not fit, until the tokens at its borders are
compatible with those outside. Two tokens are compatible when their bytes together encode to just these two; a sequence of
pairwise compatible tokens is the encoding of its bytes, so nothing outside the window can change. Decoding concatenates the
tokens' bytes up the tree over the ids.

Leaves, seams and chunks are remembered by the worker, each up to a bound; what is forgotten is encoded again.

Defined results: null and empty texts have no tokens; special tokens are ordinary text; repeated rows are each reported;
an empty table gives an empty result; only doc_id and text are read.
"""

from __future__ import annotations

import base64
import functools
import hashlib
import re
from array import array

import numpy as np
import public_tokenizers
import pyarrow as pa
import regex
from pyspark.sql import DataFrame

from graphstitch.llm.common import Memo, slices, tidy

RANKS = "byte_bpe_multi_50k.tiktoken"
LEAF_CHARS = 1 << 10
#: Pieces of at most so many bytes are merged directly.
LEAF_BYTES = 6
#: Ids joined by one step of decoding.
LEAF_IDS = 1 << 12
#: Chunks, and leaves and seams, remembered by a worker (some 200 bytes each, twice over).
MEMO, SEAMS = 250_000, 100_000
_SURE = re.compile(r"\S(?=[ \n]\S)")
_CHUNK = re.compile(r"(?<=\S)(?=[ \n]\S)")
#: White space of which not every place is sure.
_ODD = re.compile(r"[^\S \n]|[ \n]{2}|[ \n]$")


def load_ranks(path: str) -> dict[bytes, int]:
    with open(path, "rb") as f:
        return {base64.b64decode(a): int(b) for a, b in map(bytes.split, f)}


class Bpe:
    """Encoder and decoder over byte ranks."""

    def __init__(self, ranks: dict[bytes, int], pattern: str):
        self.ranks, self.pieces_of = ranks, regex.compile(pattern).findall
        self.bytes_of = [b""] * (max(ranks.values(), default=0) + 1)
        for b, i in ranks.items():
            self.bytes_of[i] = b
        self.decimal = list(map(str, range(len(self.bytes_of))))
        self.leaves: dict[bytes, tuple] = {}
        self.seams: dict[tuple, tuple] = {}
        self.old_leaves, self.old_seams = {}, {}
        self.odd = Memo(lambda chunks: list(map(self._chunk, chunks)), MEMO // 10)
        # a word stands for the chunk with a blank before it, unless it starts with a line end
        self.memo = Memo(lambda words: [self._chunk(w if w[:1] == "\n" else " " + w) for w in words], MEMO)

    def merge(self, piece: bytes) -> list[bytes]:
        """Merges of lowest rank first, the leftmost of equals. Ranks of neighbours are kept beside the parts."""
        get, none = self.ranks.get, len(self.bytes_of) + 1_000_000
        parts = [piece[i : i + 1] for i in range(len(piece))]
        ranks = [get(piece[i : i + 2], none) for i in range(len(piece) - 1)]
        while ranks and (least := min(ranks)) < none:
            i = ranks.index(least)
            parts[i : i + 2] = [new := parts[i] + parts[i + 1]]
            del ranks[i]
            if i < len(ranks):
                ranks[i] = get(new + parts[i + 1], none)
            if i:
                ranks[i - 1] = get(parts[i - 1] + new, none)
        return parts

    def leaf(self, raw: bytes) -> tuple[int, ...]:
        """Ids of a few bytes, by merging."""
        got = self.leaves.get(raw)
        if got is None:
            if len(self.leaves) >= SEAMS:
                self.old_leaves, self.leaves = self.leaves, {}
            got = self.leaves[raw] = self.old_leaves.get(raw) or tuple(map(self.ranks.__getitem__, self.merge(raw)))
        return got

    def window(self, ids: tuple[int, ...]) -> tuple[int, ...]:
        """The ids of the bytes of some tokens around a seam."""
        got = self.seams.get(ids)
        if got is None:
            if len(self.seams) >= SEAMS:
                self.old_seams, self.seams = self.seams, {}
            got = self.seams[ids] = self.old_seams.get(ids) or tuple(map(self.ranks.__getitem__, self.merge(b"".join(map(self.bytes_of.__getitem__, ids)))))
        return got

    def join(self, left: tuple[int, ...], right: tuple[int, ...]) -> tuple[int, ...]:
        a = b = 1
        near = (left[-1], right[0])
        if self.window(near) == near:
            return left + right
        while True:
            a, b = min(a, len(left)), min(b, len(right))
            window = self.window(left[len(left) - a :] + right[:b])
            fits_left = a == len(left) or self.compatible(left[-a - 1], window[0])
            fits_right = b == len(right) or self.compatible(window[-1], right[b])
            if fits_left and fits_right:
                return left[: len(left) - a] + window + right[b:]
            a, b = a * (2 - fits_left), b * (2 - fits_right)

    def compatible(self, a: int, b: int) -> bool:
        return self.window((a, b)) == (a, b)

    def piece(self, raw: bytes) -> tuple[int, ...]:
        if len(raw) <= LEAF_BYTES:
            return self.leaf(raw)
        half = len(raw) // 2
        return self.join(self.piece(raw[:half]), self.piece(raw[half:]))

    def _chunk(self, chunk: str) -> bytes:
        """Ids as 32-bit numbers."""
        ids: list[int] = []
        for piece in self.pieces_of(chunk):
            raw = piece.encode()
            whole = self.ranks.get(raw)
            if whole is not None:
                ids.append(whole)
            else:
                ids += self.piece(raw)
        return array("i", ids).tobytes()

    def _leaf_text(self, text: str) -> bytes:
        if _ODD.search(text):
            first, *rest = _CHUNK.split(text)
            return b"".join(self.odd.many([first]) + self.memo.many([c[1:] if c[0] == " " else c for c in rest]))
        # a text that follows a sure place starts with its blank; a line end before the first word encodes on its own, and is taken off again
        return b"".join(self.memo.many(("\n" + text.replace("\n", " \n")).split(" ")))[4:]

    def encode(self, text: str | None) -> bytes:
        """The ids of a text as 32-bit numbers."""
        if not text:
            return b""
        half = len(text) // 2
        if len(text) <= LEAF_CHARS:
            return self._leaf_text(text)
        behind = _SURE.search(text, half)
        b = behind.start() + 1 if behind else len(text)
        a, span = 0, 64
        while half > span // 2 and not a:  # the last sure place before the middle, looked for in growing windows
            at = max(0, half - span)
            a = max((m.start() + 1 for m in _SURE.finditer(text, at, half + 1)), default=0)
            span *= 4
        if a == 0 and b == len(text):
            return self._leaf_text(text)
        return (self.encode(text[:a]) if a else b"") + self._leaf_text(text[a:b]) + (self.encode(text[b:]) if b < len(text) else b"")

    def decode(self, ids: list[int]) -> bytes:
        """The bytes of the ids, up the tree."""
        if len(ids) <= LEAF_IDS:
            return b"".join(map(self.bytes_of.__getitem__, ids))
        half = len(ids) // 2
        return self.decode(ids[:half]) + self.decode(ids[half:])


@functools.lru_cache(2)
def encoder(path: str) -> Bpe:
    return Bpe(load_ranks(path), public_tokenizers.PATTERN)


def digests(docs: DataFrame, ranks: str | None = None) -> DataFrame:
    """Per document: doc_id, n_tokens, ids_sha256, decoded_sha256."""

    @tidy
    def run(batches):
        bpe = encoder(ranks or public_tokenizers.path(RANKS))
        for batch in (b.slice(x, y - x) for b in batches for x, y in slices(b.column("text"))):
            n, shas, plain = [], [], []
            for text in batch.column("text").to_pylist():
                ids = array("i", bpe.encode(text)).tolist()
                n.append(len(ids))
                shas.append(hashlib.sha256(",".join(map(bpe.decimal.__getitem__, ids)).encode()).hexdigest())
                plain.append(hashlib.sha256(bpe.decode(ids)).hexdigest())
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), pa.array(n, pa.int64()), pa.array(shas, pa.string()), pa.array(plain, pa.string())], ["doc_id", "n_tokens", "ids_sha256", "decoded_sha256"])

    return docs.select("doc_id", "text").mapInArrow(run, "doc_id long, n_tokens long, ids_sha256 string, decoded_sha256 string")


def tokens(docs: DataFrame, ranks: str | None = None) -> DataFrame:
    """Per document: doc_id, n_tokens, ids. Handles nulls, repeats and empty tables as stated above."""

    @tidy
    def run(batches):
        bpe = encoder(ranks or public_tokenizers.path(RANKS))
        for batch in (b.slice(x, y - x) for b in batches for x, y in slices(b.column("text"))):
            got = list(map(bpe.encode, batch.column("text").to_pylist()))
            n = np.array([len(g) // 4 for g in got], np.int64)
            ids = pa.ListArray.from_arrays(pa.array(np.concatenate([[0], np.cumsum(n)]).astype(np.int32)), pa.array(np.frombuffer(b"".join(got), np.int32)))
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), pa.array(n), ids], ["doc_id", "n_tokens", "ids"])

    return docs.select("doc_id", "text").mapInArrow(run, "doc_id long, n_tokens long, ids array<int>")
