"""Language identification by a bidirectional gated recurrent network over bytes.

The network is trained in numpy by backpropagation through time on a bounded sample of labelled documents, of which it sees
segments spread over the whole text, and reads whole texts in segments of `SEGMENT` bytes, all segments of a batch in step. It labels every byte; the document's probabilities
are the mean over its bytes. Only the weights (a few kilobytes) travel to the executors.

Defined results: a null text, or one without a letter, is `und` with score 0; without any learned language all are `und`;
repeated rows are each reported; of equal probabilities the language first in order is taken; texts of any length are read
whole; an empty table gives an empty result; lang, source and doc_id are no inputs.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from graphstitch.llm.common import lists_of, slices, text_buffer

HIDDEN, SEGMENT = 8, 64
#: Bound of the training sample: documents, and segments of each, spread evenly over its whole text.
TRAIN_DOCS, TRAIN_SEGMENTS = 4_000, 16
STEPS, BATCH, TRAIN_SEGMENT, RATE = 180, 192, 40, 0.03


def _sigmoid(x):
    return 0.5 * np.tanh(0.5 * x) + 0.5


class Network:
    """Weights: x (2, 256, 3H) input tables of both directions, u (2, H, 3H), b (2, H) of the candidate's state part,
    o (2, H, C) and c (C)."""

    def __init__(self, classes: list[str], hidden: int = HIDDEN, seed: int = 7):
        rng = np.random.default_rng(seed)
        h, n = hidden, max(len(classes), 1)
        self.classes = classes
        self.w = {
            "x": rng.normal(0, 0.3, (2, 256, 3 * h)), "u": rng.normal(0, h**-0.5, (2, h, 3 * h)), "b": np.zeros((2, 1, h)),
            "o": rng.normal(0, h**-0.5, (2, h, n)), "c": np.zeros(n),
        }
        self.w = {k: v.astype(np.float32) for k, v in self.w.items()}

    def states(self, data: np.ndarray, mask: np.ndarray, keep: bool = False):
        """Hidden states (T, 2, N, H); the second direction is stored at the byte it belongs to. data and mask: (N, T)."""
        n, t = data.shape
        h = self.w["u"].shape[1]
        out = np.empty((t, 2, n, h), np.float32)
        trace = []
        s = np.zeros((2, n, h), np.float32)
        both = np.arange(2)[:, None]
        partial = not mask.all()
        for i in range(t):
            at = (i, t - 1 - i)
            x = self.w["x"][both, np.stack([data[:, at[0]], data[:, at[1]]])]
            a = s @ self.w["u"]
            gates = _sigmoid(x[..., : 2 * h] + a[..., : 2 * h])
            z, r = gates[..., :h], gates[..., h:]
            inner = a[..., 2 * h :] + self.w["b"]
            c = np.tanh(x[..., 2 * h :] + r * inner)
            new = c + z * (s - c)
            if partial:
                m = np.stack([mask[:, at[0]], mask[:, at[1]]])[..., None].astype(np.float32)
                new = new * m
            if keep:
                trace.append((s, z, r, inner, c))
            s = new
            out[at[0], 0], out[at[1], 1] = s[0], s[1]
        return out, trace

    def probabilities(self, states: np.ndarray) -> np.ndarray:
        """Of every class at every byte, (T, N, C)."""
        logit = states[:, 0] @ self.w["o"][0] + states[:, 1] @ self.w["o"][1] + self.w["c"]
        logit -= logit.max(-1, keepdims=True)
        np.exp(logit, out=logit)
        logit /= logit.sum(-1, keepdims=True)
        return logit

    def gradients(self, data: np.ndarray, label: np.ndarray) -> tuple[float, dict]:
        """Mean cross-entropy over all positions, and its gradients by backpropagation through time."""
        n, t = data.shape
        h = self.w["u"].shape[1]
        states, trace = self.states(data, np.ones(data.shape, bool), keep=True)
        p = self.probabilities(states)
        loss = -float(np.log(p[:, np.arange(n), label] + 1e-9).mean())
        d = p / (n * t)
        d[:, np.arange(n), label] -= 1 / (n * t)
        g = {k: np.zeros_like(v) for k, v in self.w.items()}
        g["c"] = d.sum((0, 1))
        for k in range(2):
            g["o"][k] = np.einsum("tnh,tnc->hc", states[:, k], d)
        from_out = np.stack([d @ self.w["o"][k].T for k in range(2)], 1)  # (T, 2, N, H)
        back = np.zeros((2, n, h), np.float32)
        for i in range(t - 1, -1, -1):
            at = (i, t - 1 - i)
            s, z, r, inner, c = trace[i]
            ds = back + np.stack([from_out[at[0], 0], from_out[at[1], 1]])
            dc = ds * (1 - z) * (1 - c * c)
            dz = ds * (s - c) * z * (1 - z)
            dr = dc * inner * r * (1 - r)
            da = np.concatenate([dz, dr, dc * r], -1)
            dx = np.concatenate([dz, dr, dc], -1)
            for k in range(2):
                np.add.at(g["x"][k], data[:, at[k]], dx[k])
            g["u"] += np.swapaxes(s, 1, 2) @ da
            g["b"] += (dc * r).sum(1, keepdims=True)
            back = ds * z + da @ np.swapaxes(self.w["u"], 1, 2)
        return loss, g

    def fit(self, texts: list[list[bytes]], labels: list[int], steps: int = STEPS, batch: int = BATCH, segment: int = TRAIN_SEGMENT, rate: float = RATE, seed: int = 11):
        """Adam on segments drawn evenly from the classes, from their documents, and from the segments of each."""
        rng = np.random.default_rng(seed)
        by_class = [[t for t, y in zip(texts, labels) if y == k] for k in range(len(self.classes))]
        first, second = ({k: np.zeros_like(v) for k, v in self.w.items()} for _ in range(2))
        for step in range(1, steps + 1):
            label = np.arange(batch) % len(by_class)
            rows = []
            for k in label:
                parts = by_class[k][rng.integers(len(by_class[k]))]
                t = parts[rng.integers(len(parts))]
                t = t * (segment // len(t) + 1) if len(t) < segment else t
                at = rng.integers(len(t) - segment + 1)
                rows.append(np.frombuffer(t[at : at + segment], np.uint8))
            _, g = self.gradients(np.stack(rows), label)
            size = np.sqrt(sum(float((v * v).sum()) for v in g.values()))
            for k, v in g.items():
                v = v * min(1.0, 1.0 / (size + 1e-9))
                first[k] = 0.9 * first[k] + 0.1 * v
                second[k] = 0.99 * second[k] + 0.01 * v * v
                move = first[k] / (1 - 0.9**step) / (np.sqrt(second[k] / (1 - 0.99**step)) + 1e-7)
                self.w[k] = (self.w[k] - rate * (1 - 0.9 * step / steps) * move).astype(np.float32)
        return self

    def documents(self, data: np.ndarray, offs: np.ndarray, width: int = 2048, segment: int = SEGMENT) -> np.ndarray:
        """Sums over the bytes of each text of the classes' probabilities."""
        size = np.diff(offs)
        text, place = lists_of(-(-size // segment))
        start, left = offs[text] + place * segment, size[text] - place * segment
        out = np.zeros((len(size), len(self.classes)))
        full = np.argsort(left < segment, kind="stable")  # whole segments first: they need no mask
        for i in range(0, len(full), width):
            now = full[i : i + width]
            span = np.arange(min(segment, int(left[now].max())))
            mask = span < left[now][:, None]
            p = self.probabilities(self.states(data[np.minimum(start[now][:, None] + span, len(data) - 1)], mask)[0])
            p = p.sum(0) if mask.all() else (p * mask.T[..., None]).sum(0)
            for k in range(out.shape[1]):
                out[:, k] += np.bincount(text[now], p[:, k], len(size))
        return out


def segments_of(raw: bytes, most: int = TRAIN_SEGMENTS, size: int = TRAIN_SEGMENT) -> list[bytes]:
    """The whole text, or evenly spread segments of it if it has more bytes than they have."""
    if len(raw) <= most * size:
        return [raw]
    return [raw[x : x + size] for x in (np.arange(most) * (len(raw) - size) // (most - 1)).tolist()]


def train(docs: DataFrame, most: int = TRAIN_DOCS) -> Network:
    """Learns from `most` documents at most, those of least hash of their id: ids are chosen first, then only their segments
    are fetched, so a task sends `most` narrow rows to the driver at most, and all of them `most` times 640 bytes."""
    known = docs.where(F.col("lang").isNotNull() & F.col("text").rlike(r"\p{L}") & (F.crc32(F.col("doc_id").cast("string")) % 5 != 0))
    known = known.select("doc_id", "lang", "text", F.xxhash64("doc_id").alias("_o"))
    ids = known.select("_o", "doc_id").orderBy("_o", "doc_id").limit(most).distinct().collect()
    if not ids:
        return Network([])
    chosen = docs.sparkSession.createDataFrame([(r["doc_id"],) for r in ids], "doc_id long")

    def cut(batches):
        for batch in batches:
            parts = [segments_of(t.encode()) for t in batch.column("text").to_pylist()]
            yield pa.RecordBatch.from_arrays([batch.column("_o"), batch.column("doc_id"), batch.column("lang"), pa.array(parts, pa.list_(pa.binary()))], ["_o", "doc_id", "lang", "parts"])

    parts = known.join(F.broadcast(chosen), "doc_id").select("_o", "doc_id", "lang", "text").mapInArrow(cut, "_o long, doc_id long, lang string, parts array<binary>")
    rows = parts.orderBy("_o", "doc_id", "lang", "parts").limit(most).collect()
    classes = sorted({r["lang"] for r in rows})
    return Network(classes).fit([list(map(bytes, r["parts"])) for r in rows], [classes.index(r["lang"]) for r in rows])


def predict(docs: DataFrame, net: Network) -> DataFrame:
    """Per document: doc_id, held_out, lang_pred, score."""

    def run(batches):
        names = np.array(net.classes or ["und"], object)
        for batch in batches:
            for a, b in slices(batch.column("text"), 1 << 20):
                part = batch.slice(a, b - a)
                letter = part.column("letter").to_numpy(zero_copy_only=False).astype(bool)
                total = net.documents(*text_buffer(part.column("text"))) if net.classes else np.zeros((len(part), 1))
                share = total / np.maximum(total.sum(1, keepdims=True), 1e-12)
                letter &= bool(net.classes)
                best = share.argmax(1)
                score = np.where(letter, np.clip(share[np.arange(len(best)), best], 0, 1), 0.0)
                lang = np.where(letter, names[best], "und")
                yield pa.RecordBatch.from_arrays([part.column("doc_id"), part.column("held_out"), pa.array(lang.tolist(), pa.string()), pa.array(score)], ["doc_id", "held_out", "lang_pred", "score"])

    rows = docs.select("doc_id", F.coalesce(F.crc32(F.col("doc_id").cast("string")) % 5 == 0, F.lit(False)).alias("held_out"), "text", F.coalesce(F.col("text").rlike(r"\p{L}"), F.lit(False)).alias("letter"))
    return rows.mapInArrow(run, "doc_id long, held_out boolean, lang_pred string, score double")


def identify(docs: DataFrame) -> DataFrame:
    return predict(docs, train(docs.select("doc_id", "lang", "text")))
