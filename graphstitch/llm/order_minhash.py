"""Near-duplicate detection by order MinHash, verified by banded alignment.

A text of `LONG` words or more is cut into k-mers of five words, labelled with their occurrence number. They are dealt to bins
by hash, and of each bin the two of least hash, in text order, are one sketch; short texts are dealt several times into
fewer bins (`TIERS`). A text of up to `SHORT` words is named by all its runs of three words (of two at 4 and 5 words, by the
whole text below): texts of edit similarity >= `SIMILARITY` always share such a run, so short texts never miss. Equal texts
are merged first; distinct texts that share a name are a bucket.

Every pair of a bucket is settled, in four rounds of links and components: members meet the first one of their largest
bucket, then buckets of two meet that are still apart; then, in one bucket for each two components that still share
some, each member meets the likeliest one of another component; then all that are left in any. There a component is one row of
a bucket, with the least and most words of its members in each bin; members of two components meet, once and not by bucket,
only if these leave room for a link. Before texts are aligned a pair must pass a bound that no link breaks: counts of words in
`BINS` bins differ by one per edit at most. Pairs are aligned word by word inside a band and linked when 1 - distance /
longer length >= `SIMILARITY`. Classes are the connected components of the links, found by distributed label propagation.

Scale: names (some 100 of 8 bytes a text) are shuffled once, to be counted; buckets of two are pairs at once, members of the
others are fetched by a join with the buckets, broadcast only up to a counted bound. Texts are moved for pairs that met, in
the first round one pair a text, in the last two once for each two groups of `GROUP` texts with pairs. Large buckets of several
components are dealt out in blocks of `BLOCK` members, or components in the last round; the pairs of counts compared grow with
the square of these, their rows with that square over `BLOCK`. Components are found over all texts
once; later links join labels, up to `FEW_LINKS` of them in one task. Nothing but row counts reaches the driver. Of long
texts with random changes exactly at the similarity bound 93 % or more share a sketch (measured, and tested), at 0.85 more
than 99 %.

Defined results: null and empty texts are equal to each other and form one class; so do texts of blanks only with equal
blanks; a class is named after its least doc_id (null only if all are) and told from others of that id by its label; repeated rows
are in one class; an empty table gives an empty result; other columns pass through `keep_one` untouched. Distinct texts are known by a 64-bit hash.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from graphstitch.llm import common
from graphstitch.llm.common import grams, lists_of, mix, pair, slices, text_buffer, tidy, word_names

GRAM, SIMILARITY = 5, 0.8
#: For texts of so many k-mers at least: rounds of dealing, and bins of each. The fewer the k-mers, the fewer the bins.
TIERS = [(240, 1, 80), (120, 2, 40), (60, 6, 20), (0, 32, 5)]
#: Texts of LONG words on have sketches, texts up to SHORT words all their runs; LONG <= 0.8 * (SHORT + 1).
LONG, SHORT, BINS, BLOCK = 25, 30, 256, 1024
#: Texts of a group where many pairs of few texts are aligned.
GROUP = 128
#: Components of several members that a task holds while it puts their members together (some 600 bytes each).
BOXES = 20_000
#: Buckets of a component that are listed beside it, so that its pairs come out once; components of more have no list, and their
#: pairs may come out once for each bucket.
LISTED = 256
#: Links between components that one task may join.
FEW_LINKS = 20_000


def labelled_grams(x: np.ndarray, first: np.ndarray, k: int = GRAM) -> tuple[np.ndarray, np.ndarray]:
    """Names of the k-mers with their occurrence numbers, text by text, and how many each text has."""
    n = np.diff(first)
    many = np.where(n >= k, n - k + 1, np.minimum(n, 1))
    text, place = lists_of(many)
    at = first[text] + place
    whole = grams(x, k)
    name = whole[np.minimum(at, max(len(whole) - 1, 0))] if len(whole) else np.zeros(len(at), np.uint64)
    for i in np.flatnonzero((n > 0) & (n < k)):  # a short text is one k-mer
        name[np.searchsorted(text, i)] = grams(x[first[i] : first[i + 1]], int(n[i]))[0]
    key = pair(name, text.astype(np.uint64), 5)
    order = np.argsort(key, kind="stable")
    fresh = np.concatenate([[True], key[order][1:] != key[order][:-1]]) if len(order) else np.empty(0, bool)
    if not fresh.all():
        run = np.flatnonzero(fresh)
        nth = np.arange(len(order)) - np.repeat(run, np.diff(np.append(run, len(order))))
        occurrence = np.empty(len(order), np.int64)
        occurrence[order] = nth
        later = np.flatnonzero(occurrence)
        name[later] = pair(name[later], occurrence[later].astype(np.uint64), 6)
    return name, many


def tier_of(many: np.ndarray) -> np.ndarray:
    """The tier of texts of so many k-mers."""
    return np.searchsorted(-np.array([t[0] for t in TIERS]), -many)


def sketches(name: np.ndarray, many: np.ndarray, tier: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Sketches of texts, each dealt as its tier says (none below tier 0): text and sketch. Each round deals the k-mers to bins by hash; of each
    bin the two of least hash are named in text order. A bin of one k-mer has no sketch."""
    texts, codes = [], []
    for k, (_, rounds, bins) in enumerate(TIERS):
        chosen = np.flatnonzero((tier == k) & (many > 0))
        if not len(chosen):
            continue
        text, place = lists_of(many[chosen])
        at = (np.cumsum(many) - many)[chosen][text] + place
        for t in range(rounds):
            value = mix(name[at] ^ np.uint64((64 * k + t + 1) * 0xD6E8FEB86659FD93 % 2**64))
            slot = value % np.uint64(bins)
            packed = (text.astype(np.uint64) << np.uint64(45)) | (slot << np.uint64(38)) | (value >> np.uint64(26))
            order = np.argsort(packed)
            group = packed[order] >> np.uint64(38)
            head = np.flatnonzero(np.concatenate([[True], group[1:] != group[:-1]]))
            head = head[np.diff(np.append(head, len(group))) > 1]
            x, y = at[order[head]], at[order[head + 1]]
            code = pair(name[np.minimum(x, y)], name[np.maximum(x, y)], 11)
            codes.append(pair(code, (slot[order[head]] * np.uint64(64) + np.uint64(t)) * np.uint64(len(TIERS)) + np.uint64(k), 12))
            texts.append(chosen[text[order[head]]])
    none = np.empty(0, np.int64)
    return np.concatenate([none, *texts]), np.concatenate([none.astype(np.uint64), *codes])


def runs_of(x: np.ndarray) -> np.ndarray:
    """Names of a short text: texts whose distance is a fifth of the longer one's words at most share one."""
    if len(x) < 4:
        return grams(x, len(x))
    some = [pair(grams(x, k), np.uint64(k), 7) for k in (2, 3) if (k == 2) == (len(x) < 5) or len(x) == 5]
    return np.unique(np.concatenate(some))


def word_counts(name: np.ndarray, first: np.ndarray) -> np.ndarray:
    """Words per bin, at most 255; one edit changes two bins by one, up and down, at most."""
    n = len(first) - 1
    text = np.repeat(np.arange(n), np.diff(first))
    return np.minimum(np.bincount(text * BINS + (name % np.uint64(BINS)).astype(np.int64), minlength=n * BINS), 255).astype(np.uint8).reshape(n, BINS)


def names_of(words: np.ndarray, first: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Names under which texts are looked for: text (ascending) and name."""
    n = np.diff(first)
    name, many = labelled_grams(words, first)
    tier = np.where(n >= LONG, tier_of(many), -1)
    # a text's partners may be a fifth shorter, and of the next tier
    below = tier_of(np.ceil(SIMILARITY * n).astype(np.int64) - GRAM + 1)
    found = [sketches(name, many, tier), sketches(name, many, np.where((below != tier) & (tier >= 0), below, -1))] if len(name) else []
    for i in np.flatnonzero((n > 0) & (n <= SHORT)):
        runs = runs_of(words[first[i] : first[i + 1]])
        found.append((np.full(len(runs), i), runs))
    text, code = (np.concatenate([np.empty(0, kind), *(f[k] for f in found)]) for k, kind in ((0, np.int64), (1, np.uint64)))
    order = np.argsort(text, kind="stable")
    return text[order], code[order]


@tidy
def _sketch(batches):
    for batch in batches:
        for a, b in slices(batch.column("text"), 2 << 20):
            part = batch.slice(a, b - a)
            data, offs = text_buffer(part.column("text"))
            starts, ends, first = common.spans(data, offs)
            words = word_names(data, starts, ends)
            text, code = names_of(words, first)
            sizes = np.bincount(text, minlength=len(part))
            sk = pa.ListArray.from_arrays(pa.array(np.concatenate([[0], np.cumsum(sizes)]).astype(np.int32)), pa.array(code.view(np.int64)))
            yield pa.RecordBatch.from_arrays([part.column("doc_id"), part.column("h"), pa.array(np.diff(first).astype(np.int64)), sk, _binary(word_counts(words, first))], ["doc_id", "h", "many", "sk", "counts"])


def _binary(x: np.ndarray) -> pa.Array:
    at = np.arange(len(x) + 1, dtype=np.int32) * BINS
    return pa.Array.from_buffers(pa.binary(), len(x), [None, pa.py_buffer(at), pa.py_buffer(np.ascontiguousarray(x))])


def _table(column: pa.Array) -> np.ndarray:
    """The counts of a binary column, one row each."""
    _, offsets, data = column.buffers()
    at = np.frombuffer(offsets, np.int32)[column.offset]
    return np.frombuffer(data, np.uint8)[at : at + len(column) * BINS].reshape(len(column), BINS)


def _edits(counts_a, counts_b) -> np.ndarray:
    """Edits that the word counts ask for: words of the one that the other lacks, or the other way round."""
    most = np.maximum(counts_a, counts_b).sum(-1, dtype=np.int64)
    return most - np.minimum(counts_a.sum(-1, dtype=np.int64), counts_b.sum(-1, dtype=np.int64))


def room_between(counts_a, counts_b, many_a, many_b) -> np.ndarray:
    """How many edits the word counts leave up to the bound of a link; never below 0 for texts that are alike."""
    longest = np.maximum(many_a, many_b)
    return ((1 - SIMILARITY) * longest + 1e-9).astype(np.int64) - np.maximum(_edits(counts_a, counts_b), np.abs(many_a - many_b))


def room_of_boxes(low_a, high_a, low_b, high_b, least_a, most_a, least_b, most_b) -> np.ndarray:
    """The same for two components, of which the least and most words per bin and in all are known: never less than the room of
    a text of the one and a text of the other."""
    missing = np.maximum(low_a, high_b).sum(-1, dtype=np.int64) - high_b.sum(-1, dtype=np.int64)
    added = np.maximum(low_b, high_a).sum(-1, dtype=np.int64) - high_a.sum(-1, dtype=np.int64)
    apart = np.maximum(np.maximum(missing, added), np.maximum(least_a - most_b, least_b - most_a))
    return ((1 - SIMILARITY) * np.maximum(most_a, most_b) + 1e-9).astype(np.int64) - apart


@tidy
def _boxes(batches):
    """Rows of one component put together: members, least and most words in all and per bin. Where the rows of a component
    follow each other it comes out once, otherwise perhaps several times."""
    held: dict = {}

    def give(but=None):
        names = [x for x in held if x != but]
        cols = list(zip(*(held.pop(x) for x in names)))
        numbers = [pa.array(names, pa.int64()), *(pa.array(np.array(c, np.int64)) for c in cols[:3])]
        return pa.RecordBatch.from_arrays([*numbers, *(_binary(np.stack(c)) for c in cols[3:])], ["label", "members", "least", "most", "low", "high"])

    for batch in batches:
        if not len(batch):
            continue
        label = batch.column("label").to_numpy()
        order = np.argsort(label, kind="stable")
        at = np.flatnonzero(np.concatenate([[True], np.diff(label[order]) != 0]))
        got = [f.reduceat(batch.column(c).to_numpy()[order], at).tolist() for f, c in ((np.add, "members"), (np.minimum, "least"), (np.maximum, "most"))]
        got += [f.reduceat(_table(batch.column(c))[order], at, axis=0) for f, c in ((np.minimum, "low"), (np.maximum, "high"))]
        for name, n, a, b, low, high in zip(label[order][at].tolist(), *got):
            if name in held:
                more, least, most, lows, highs = held[name]
                n, a, b, low, high = n + more, min(a, least), max(b, most), np.minimum(low, lows), np.maximum(high, highs)
            held[name] = (n, a, b, low, high)
        if len(held) > BOXES:
            yield give(int(label[-1]))
    if held:
        yield give()


def _blocks(settle, numbers: list[str], counts: list[str], out_names: list[str], lists: tuple = ()):
    """Over rows sorted by bucket and block: what `settle` adds to a list for each block, every row of it once."""

    @tidy
    def run(batches):
        held: list = []

        def finish():
            out: list = []
            t = pa.Table.from_batches(held).combine_chunks().to_batches()[0]
            cols = {c: t.column(c).to_numpy() for c in ("part", *numbers)} | {c: _table(t.column(c)) for c in counts} | {c: t.column(c).to_pylist() for c in lists}
            s, i, j = (t.column(c).to_numpy() for c in ("s", "i", "j"))
            cuts = np.flatnonzero((np.diff(s) != 0) | (np.diff(i) != 0) | (np.diff(j) != 0)) + 1
            for a, b in zip([0, *cuts], [*cuts, len(s)]):
                settle({c: x[a:b] for c, x in cols.items()} | {"s": s[a]}, i[a], j[a], out)
            held.clear()
            found = list(zip(*set(out))) or [()] * len(out_names)
            return pa.RecordBatch.from_arrays([pa.array(x, pa.int64()) for x in found], out_names)

        for batch in batches:
            if not len(batch):
                continue
            key = [batch.column(c).to_numpy() for c in ("s", "i", "j")]
            # rows of the last block may go on in the next batch
            last = int(np.flatnonzero(np.any([k != k[-1] for k in key], axis=0))[-1]) + 1 if any((k != k[-1]).any() for k in key) else 0
            if last or held and any(held[-1].column(c)[-1].as_py() != batch.column(c)[0].as_py() for c in ("s", "i", "j")):
                if last:
                    held.append(batch.slice(0, last))
                yield finish()
            held.append(batch.slice(last))
        if held:
            yield finish()

    return run


def _across(every: bool):
    """Pairs of texts of different components that pass the bound: all of them, or for each member the one with most room."""

    def one_way(c, i, j, out):
        h, label, many, counts = (c[x] for x in ("h", "label", "many", "counts"))
        rows, cols = (np.flatnonzero(c["part"] == x) for x in (i, j))
        for x in rows:
            longest = np.maximum(many[cols], many[x])
            other = cols[(label[cols] != label[x]) & (np.abs(many[cols] - many[x]) <= (1 - SIMILARITY) * longest + 1e-9) & ((h[cols] > h[x]) if every and i == j else True)]
            if len(other):
                room = room_between(counts[x], counts[other], many[x], many[other])
                near = other[room >= 0] if every else other[[room.argmax()]] if room.max() >= 0 else ()
                out += [(min(h[x], h[y]), max(h[x], h[y])) for y in near]

    def settle(c, i, j, out):
        one_way(c, i, j, out)
        if not every and i != j:
            one_way(c, j, i, out)

    return _blocks(settle, ["h", "label", "many"], ["counts"], ["a", "b"])


def _meet():
    """Pairs of components that may have a pair within the bound. Where one has several members the larger comes first, and
    `more` is 1. A pair that shares several buckets comes out in the least of them, where the lists of `buckets` of both are known."""

    def settle(c, i, j, out):
        label, members, least, most, low, high = (c[x] for x in ("label", "members", "least", "most", "low", "high"))
        buckets = [b and set(b) for b in c["buckets"]]
        rows, cols = (np.flatnonzero(c["part"] == x) for x in (i, j))
        for x in rows:
            longest = np.maximum(most[cols], most[x])
            far = np.maximum(least[cols] - most[x], least[x] - most[cols]) > (1 - SIMILARITY) * longest + 1e-9
            other = cols[~far & ((label[cols] > label[x]) if i == j else True)]
            if len(other):
                room = room_of_boxes(low[x], high[x], low[other], high[other], least[x], most[x], least[other], most[other])
                for y in other[room >= 0]:
                    if buckets[x] and buckets[y] and min(buckets[x] & buckets[y]) != c["s"]:
                        continue
                    a, b = sorted((x, y), key=lambda z: (-members[z], label[z]))
                    out.append((label[a], label[b], int(members[a] > 1)))

    return _blocks(settle, ["label", "members", "least", "most"], ["low", "high"], ["a", "b", "more"], ("buckets",))


def distance_within(a: list, b: list, k: int) -> int | None:
    """Edit distance of two sequences if it is k at most, else None. Bit-parallel over the band of 2k + 1 diagonals."""
    if len(a) < len(b):
        a, b = b, a
    n, m = len(a), len(b)
    k = min(k, n)
    if n - m > k:
        return None
    if not m:
        return n
    place: dict = {}
    for i, w in enumerate(a):
        place.setdefault(w, []).append(i + k)
    found = {}
    for w in set(b) & place.keys():
        bits = bytearray((n + k) // 8 + 1)
        for i in place[w]:
            bits[i >> 3] |= 1 << (i & 7)
        found[w] = int.from_bytes(bits, "little")
    width = 2 * k + 1
    mask, top = (1 << width) - 1, 1 << (width - 1)
    up, down, d = mask & ~((1 << k) - 1), 0, k
    edge = top >> 1
    for j, w in enumerate(b):
        x = (found.get(w, 0) >> j) & mask
        diag = (((((x & up) + up) ^ up) | x | down)) & mask
        plus = down | (mask & ~(diag | up))
        minus = diag & up
        if j < n - k:
            d += not diag & top
            if d > 2 * k + m - n:
                return None
        else:
            d += bool(plus & edge) - bool(minus & edge)
            edge >>= 1
        up = minus | (mask & ~((diag >> 1) | plus))
        down = (diag >> 1) & plus
    return d if d <= k else None


def alike(a: list, b: list, similarity: float = SIMILARITY) -> bool:
    """Whether the edit similarity reaches the bound; the band starts narrow, as most copies are close, and widens up to it."""
    longest = max(len(a), len(b))
    most = int((1 - similarity) * longest + 1e-9)
    # equal ends cost nothing
    at = next((i for i, (x, y) in enumerate(zip(a, b)) if x != y), min(len(a), len(b)))
    a, b = a[at:], b[at:]
    at = next((i for i, (x, y) in enumerate(zip(reversed(a), reversed(b))) if x != y), min(len(a), len(b)))
    a, b = a[: len(a) - at], b[: len(b) - at]
    k = 48
    while k < most:
        if distance_within(a, b, k) is not None:
            return True
        k *= 4
    return distance_within(a, b, most) is not None


@tidy
def _verify(batches):
    """Pairs a, b that pass the bound of the word counts, and then the alignment."""
    kept: tuple = (None, None)
    for batch in (b.slice(x, y - x) for b in batches for x, y in slices(b.column("ta"), 1 << 20)):
        ma, mb = (batch.column(c).to_numpy() for c in ("ma", "mb"))
        good = room_between(_table(batch.column("ca")), _table(batch.column("cb")), ma, mb) >= 0
        out = []
        for a, b, ta, tb in zip(*(batch.column(c).filter(pa.array(good)).to_pylist() for c in ("a", "b", "ta", "tb"))):
            if kept[0] != b:
                kept = (b, tb.encode().split())
            if alike(ta.encode().split(), kept[1]):
                out.append((a, b))
        a, b = zip(*out) if out else ((), ())
        yield pa.RecordBatch.from_arrays([pa.array(a, pa.int64()), pa.array(b, pa.int64())], ["a", "b"])


@tidy
def _align(batches):
    """Over the members of each group, in order: h, label, text and the members `others` it is to be compared with. A pair is
    aligned unless links found before it in the group join its components already."""
    group, held, out = None, {}, []

    def settle():
        up: dict[int, int] = {}

        def root(x):
            while up.setdefault(x, x) != x:
                x = up[x]
            return x

        for a, (label, ta, others) in held.items():
            for b in others:
                x, y = root(label), root(held[b][0])
                if x != y and alike(ta, held[b][1]):
                    up[max(x, y)] = min(x, y)
                    out.append((a, b))
        held.clear()

    for batch in batches:
        for s, h, label, text, others in zip(*(batch.column(c).to_pylist() for c in ("s", "h", "label", "text", "others"))):
            if s != group:
                settle()
                group = s
            held[h] = (label, text.encode().split(), others)
    settle()
    yield pa.RecordBatch.from_arrays([pa.array(x, pa.int64()) for x in (zip(*out) if out else ((), ()))], ["a", "b"])


@tidy
def _union(batches):
    """Node and least node of its component, for a bounded number of links."""
    up: dict[int, int] = {}

    def root(x):
        while up.setdefault(x, x) != x:
            up[x] = x = up[up[x]]
        return x

    for batch in batches:
        for a, b in zip(batch.column("a").to_pylist(), batch.column("b").to_pylist()):
            a, b = root(a), root(b)
            up[max(a, b)] = min(a, b)
    yield pa.RecordBatch.from_arrays([pa.array(list(up), pa.int64()), pa.array([root(x) for x in list(up)], pa.int64())], ["node", "label"])


def components(links: DataFrame, few: int = FEW_LINKS) -> DataFrame:
    """links: a, b. Returns node, label: the least node of each connected component. Up to `few` links, by their count, go to
    one task; beyond, each round takes the least label around and then the label's own label; rounds end when nothing changes."""
    if links.count() <= few:
        return common.cut(links.repartition(1).mapInArrow(_union, "node long, label long"))
    both = common.cut(links.select("a", "b").union(links.select("b", "a")).distinct())
    labels = common.cut(both.groupBy(F.col("a").alias("node")).agg(F.least(F.min("b"), F.first("a")).alias("label")))
    while True:
        around = both.join(labels, both["b"] == labels["node"]).select(F.col("a").alias("node"), "label")
        near = around.union(labels).groupBy("node").agg(F.min("label").alias("label"))
        own = labels.select(F.col("node").alias("_n"), F.col("label").alias("_l"))
        ahead = near.join(own, near["label"] == own["_n"], "left").select("node", F.least("label", F.coalesce("_l", "label")).alias("label"))
        new = common.cut(ahead)
        old = labels.select(F.col("node").alias("_n"), F.col("label").alias("_l"))
        done = new.join(old, (new["node"] == old["_n"]) & (new["label"] != old["_l"])).isEmpty()
        common.forget(labels)
        if done:
            common.forget(both)
            return new
        labels = new


def joined(comp: DataFrame, links: DataFrame) -> DataFrame:
    """Components after further links between them: only the labels are joined, and the old ones renamed."""
    named = links.join(common.small(comp).toDF("a", "_a"), "a", "left").join(common.small(comp).toDF("b", "_b"), "b", "left")
    more = common.cut(named.select("a", "b", F.coalesce("_a", "a").alias("la"), F.coalesce("_b", "b").alias("lb")))
    up = components(more.select(F.col("la").alias("a"), F.col("lb").alias("b")).where("a <> b").distinct())
    nodes = comp.union(more.select("a", "la")).union(more.select("b", "lb")).distinct()
    out = nodes.join(common.small(up).toDF("label", "_up"), "label", "left").select("node", F.coalesce("_up", "label").alias("label"))
    out = common.cut(out)
    common.forget(comp, more, up)
    return out


def classes(docs: DataFrame, few: int = FEW_LINKS) -> DataFrame:
    """Per distinct text: h (its hash), label (of its class), class_id, members, links; class_id is the least doc_id."""
    texts = docs.select("doc_id", F.coalesce("text", F.lit("")).alias("text")).withColumn("h", F.xxhash64("text"))
    sk = texts.mapInArrow(_sketch, "doc_id long, h long, many long, sk array<long>, counts binary")
    # equal texts have equal sketches; the arrays are carried as one value per text and combined before the shuffle
    distinct = sk.groupBy("h").agg(F.min("doc_id").alias("rep"), F.count("*").alias("copies"), F.max("sk").alias("sk"), F.max("many").alias("many"), F.max("counts").alias("counts"))
    distinct = common.cut(distinct)
    rows = distinct.where("many > 0").select("h", F.explode("sk").alias("s"))
    buckets = common.cut(rows.groupBy("s").agg(F.min("h").alias("lo"), F.max("h").alias("hi"), F.count("*").alias("n")).where("n > 1"))
    # most buckets are of two and need no second look at the names; members of the others are fetched
    several = buckets.where("n > 2").select("s", "lo", "n")
    rows = common.cut(rows.join(common.small(several), "s").select("s", "h", "lo", "n"))
    met = rows.where("h <> lo").select("h", "lo", "n").union(buckets.where("n = 2").select("hi", "lo", "n"))
    met = common.cut(met.groupBy("h", "lo").agg(F.max("n").alias("n")))
    wanted = met.select("h").union(met.select("lo")).distinct()
    wanted = common.cut(wanted.join(distinct.select("h", "rep", "many", "counts"), "h").select(F.col("h").alias("_h"), "rep", "many", "counts"))
    # one text of each distinct one that met another: found by its id, so most texts stay where they are
    ids = common.small(wanted.select("_h", "rep"))
    held = texts.join(ids, (texts["h"] == ids["_h"]) & texts["doc_id"].eqNullSafe(ids["rep"])).select("h", "text").dropDuplicates(["h"])
    held = common.cut(held.join(wanted.select(F.col("_h").alias("h"), "many", "counts"), "h"))

    def linked(pairs: DataFrame) -> DataFrame:
        ab = pairs.join(held.toDF("a", "ta", "ma", "ca"), "a").join(held.toDF("b", "tb", "mb", "cb"), "b")
        return common.cut(ab.select("a", "b", "ta", "tb", "ma", "mb", "ca", "cb").mapInArrow(_verify, "a long, b long"))

    def settled(pairs: DataFrame, comp: DataFrame) -> DataFrame:
        """Links among many pairs of few texts. Texts fall into groups of some `GROUP`; one is moved once for each two groups
        in which it has a pair, not for each pair."""
        groups = 1 + pairs.select("a").union(pairs.select("b")).distinct().count() // GROUP
        place = lambda c: F.pmod(F.xxhash64(F.lit(9), c), F.lit(groups))
        own = pairs.select("a", "b", (place("a") * groups + place("b")).alias("s"))
        asks = own.groupBy("s", F.col("a").alias("h")).agg(F.collect_list("b").alias("others"))
        none = own.select("s", F.col("b").alias("h"), F.array().cast("array<long>").alias("others")).distinct()
        member = asks.union(none).groupBy("s", "h").agg(F.flatten(F.collect_list("others")).alias("others"))
        member = common.cut(member)
        ab = member.join(held.select("h", "text"), "h").join(common.small(comp).withColumnRenamed("node", "h"), "h", "left")
        ab = ab.select("s", "h", F.coalesce("label", "h").alias("label"), "text", "others").repartition("s").sortWithinPartitions("s")
        out = common.cut(ab.mapInArrow(_align, "a long, b long"))
        common.forget(member)
        return out

    # first each member meets the first one of its largest bucket only; then buckets of two whose members are still apart
    one = met.groupBy("h").agg(F.max(F.struct("n", "lo")).alias("_x")).select(F.col("h").alias("a"), F.col("_x.lo").alias("b"))
    found = [linked(one)]
    comp = components(found[0], few)
    known = common.small(comp)
    apart = met.where("n = 2").join(known.toDF("h", "_a"), "h", "left").join(known.toDF("lo", "_b"), "lo", "left")
    apart = apart.where(F.coalesce("_a", "h") != F.coalesce("_b", "lo")).select(F.col("h").alias("a"), F.col("lo").alias("b"))
    found.append(linked(apart))
    comp = joined(comp, found[-1])
    def dealt(members: DataFrame) -> DataFrame:
        """Members of buckets of `n` in blocks of `BLOCK`, each block with itself and every other one."""
        parts = F.ceil(F.col("n") / BLOCK)
        own = members.withColumn("part", F.pmod(F.xxhash64("h", "s"), parts)).withColumn("o", F.explode(F.sequence(F.lit(0).cast("long"), parts - 1)))
        own = own.withColumns({"i": F.least("part", "o"), "j": F.greatest("part", "o")}).drop("o", "n")
        return own.repartition("s", "i", "j").sortWithinPartitions("s", "i", "j")

    def members_now() -> DataFrame:
        live = rows.join(common.small(comp).withColumnRenamed("node", "h"), "h", "left")
        return live.select("s", "n", "h", F.coalesce("label", "h").alias("label"))

    sizes = held.select("h", "many", "counts")
    # only to have fewer components: in one bucket for each two that still share some, the largest, each member meets one
    live = members_now()
    mixed = live.groupBy("s").agg(F.min("label").alias("_a"), F.max("label").alias("_b"), F.count("*").alias("_n")).where("_a <> _b")
    mixed = common.cut(mixed.groupBy("_a", "_b").agg(F.max(F.struct("_n", "s")).alias("_m")).select("_m.s"))
    live = live.join(common.small(mixed), "s", "left_semi").join(sizes, "h")
    pairs = common.cut(dealt(live).mapInArrow(_across(False), "a long, b long").distinct())
    found.append(settled(pairs, comp))
    comp = joined(comp, found[-1])
    common.forget(mixed, pairs)
    # then components meet as a whole, one row each in a bucket, however many members they have there
    one = F.lit(1).cast("long").alias("members")
    box = lambda t: t.select("label", one, F.col("many").alias("least"), F.col("many").alias("most"), F.col("counts").alias("low"), F.col("counts").alias("high"))
    kind = "label long, members long, least long, most long, low binary, high binary"
    several = box(sizes.join(common.small(comp).withColumnRenamed("node", "h"), "h")).mapInArrow(_boxes, kind)
    several = several.repartition("label").sortWithinPartitions("label").mapInArrow(_boxes, kind)
    shape = common.cut(several.union(box(sizes.join(common.small(comp), sizes["h"] == F.col("node"), "left_anti").withColumnRenamed("h", "label"))))
    # buckets of the same components (by their number and the sum of their hashes) are settled once
    owners = common.cut(members_now().select("s", "n", "label").distinct())
    mixed = owners.groupBy("s").agg(F.min("label").alias("_a"), F.max("label").alias("_b"), F.bit_xor(F.xxhash64("label")).alias("_x"), F.count("*").alias("_n")).where("_a <> _b")
    mixed = common.cut(mixed.groupBy("_x", "_n", "_a", "_b").agg(F.min("s").alias("s")).select("s"))
    asked = common.cut(owners.join(common.small(mixed), "s", "left_semi"))
    listed = asked.groupBy("label").agg(F.count("*").alias("_n")).where(F.col("_n") <= LISTED).select("label")
    listed = asked.join(listed, "label", "left_semi").groupBy("label").agg(F.collect_list("s").alias("buckets"))
    live = asked.withColumn("h", F.col("label")).join(shape.join(listed, "label", "left"), "label")
    near = common.cut(dealt(live).drop("h").mapInArrow(_meet(), "a long, b long, more long").distinct())
    # members of a component of several meet those of all that may be near it, once
    wide = near.where("more = 1").select(F.col("a").alias("s"), "b")
    inside = wide.select("s").distinct().join(common.small(comp), F.col("s") == F.col("label")).select("s", F.col("node").alias("h"), F.lit(1).cast("long").alias("label"))
    around = wide.join(common.small(comp), F.col("b") == F.col("label"), "left").select("s", F.coalesce("node", "b").alias("h"), F.lit(0).cast("long").alias("label"))
    both = common.cut(inside.union(around))
    counted = common.cut(both.groupBy("s").agg(F.count("*").alias("n")))
    pairs = dealt(both.join(common.small(counted), "s").join(sizes, "h")).mapInArrow(_across(True), "a long, b long").distinct()
    pairs = common.cut(pairs.union(near.where("more = 0").select(F.least("a", "b"), F.greatest("a", "b"))))
    found.append(settled(pairs, comp))
    comp = joined(comp, found[-1])
    common.forget(mixed, pairs, shape, owners, asked, near, both, counted)
    links = found[0].union(found[1]).union(found[2]).union(found[3]).distinct()
    degree = links.select(F.col("a").alias("h")).union(links.select(F.col("b").alias("h"))).groupBy("h").agg(F.count("*").alias("links"))
    out = distinct.select("h", "rep", "copies").join(common.small(comp).withColumnRenamed("node", "h"), "h", "left").join(degree, "h", "left")
    out = out.select("h", "rep", "copies", F.coalesce("label", "h").alias("label"), F.coalesce("links", F.lit(0)).alias("links"))
    named = out.groupBy("label").agg(F.min("rep").alias("class_id"), F.sum("copies").alias("members"))
    done = common.cut(out.join(named, "label").select("h", "label", "class_id", "members", (F.col("links") + F.col("copies") - 1).alias("links")))
    common.forget(distinct, buckets, rows, met, wanted, held, comp, *found)
    return done


def membership(docs: DataFrame) -> DataFrame:
    """Per document: doc_id, class_id, label (differs between classes, also where ids are repeated or null), members
    (documents in the class), links (equal texts and linked texts)."""
    texts = docs.select("doc_id", F.xxhash64(F.coalesce("text", F.lit(""))).alias("h"))
    return texts.join(classes(docs), "h").select("doc_id", "class_id", "label", "members", "links")


def keep_one(docs: DataFrame) -> DataFrame:
    """Of each class one document that names it stays, with all its columns; of equal rows, one."""
    h = F.xxhash64(F.coalesce("text", F.lit("")))
    ids = docs.select("doc_id", h.alias("_h")).groupBy("doc_id", "_h").agg(F.count("*").alias("_same"))
    least = F.min(F.struct(F.col("doc_id").isNull().alias("_n"), F.col("doc_id").alias("_d"), "_h", "_same")).alias("_first")
    first = ids.join(classes(docs).select(F.col("h").alias("_h"), "label"), "_h").groupBy("label").agg(least)
    first = common.cut(first.select("_first._d", "_first._h", "_first._same"))
    name = "_gs_h"
    while name in docs.columns:
        name += "_"
    marked = docs.withColumn(name, h)
    out = marked.join(first, marked["doc_id"].eqNullSafe(first["_d"]) & (marked[name] == first["_h"]), "left_semi")
    if not first.where("_same > 1").isEmpty():
        out = out.dropDuplicates(["doc_id", name])
    return out.drop(name)
