"""Substring dedup by recompression: words covered by a repeated window are removed.

Each text is parsed bottom-up in rounds: maximal runs of one symbol get one name, then neighbours (a, b) whose coins are
0 and 1 get one name. Names and coins come from the content alone, so all tasks name alike and equal passages have equal
symbols inside. Every symbol carries the word interval on which its existence depends. A window of `window` words is filed
under the least-named symbol whose interval lies inside it, a choice that reads nothing outside the window: equal windows
are always filed under equal names. (A window without such a symbol, as inside a long run, is filed under its own name.)
Symbols that occur once are then alone under their name; under shared names, windows are verified by 40 more bits of their
content, at equal places relative to the symbol. So no repeat is lost, and a false one needs a 104-bit accident.

Scale: one exchange of about a twelfth as many rows as words, by name; names with more than about `hot` rows leave that path
and are settled by counts that combine before their shuffle, and a join that adaptive execution can split. No pairs are made.
The texts are parsed once for either path, and a sixteenth of them before, to tell the paths apart.

Defined results: null and blank texts have no words; texts shorter than a window keep all; repeated rows are each other's
copies, so both lose their windows; rows are known by doc_id and a 64-bit hash of the text, so repeated or null ids do no harm; an empty table
gives an empty result; other columns pass through `remove_repeats` untouched.
"""

from __future__ import annotations

import hashlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from graphstitch.llm import common
from graphstitch.llm.common import grams, lists_of, mix, pair, slices, text_buffer, word_names, tidy

WINDOW = 35
ROUNDS = 3
#: Rows under one name beyond which the name leaves the grouping path.
HOT = 100_000
#: Names are judged by every HOT_PART-th row.
HOT_PART = 16
#: Hot names that may be broadcast (8 bytes each); beyond, a shuffled join.
HOT_BROADCAST = 200_000

#: In place of a symbol's place: a stretch of windows that is settled already.
SETTLED = -1
FILED = "name long, doc_id long, th long, lead int, first int, body binary"
SPAN = "doc_id long, th long, a int, b int"


def parse(x: np.ndarray, first: np.ndarray, rounds: int = ROUNDS) -> tuple[np.ndarray, ...]:
    """Symbols of texts laid end to end: names, first words, and dependence intervals [left, right)."""
    n = len(x)
    text = np.repeat(np.arange(len(first) - 1), np.diff(first))
    name, lo = x.copy(), np.arange(n)
    left, right = lo.copy(), lo + 1
    for r in range(rounds):
        if not len(name):
            break
        # the symbols before and after; a text's border counts as unknown, beyond every window
        border = text[1:] != text[:-1]
        before = np.concatenate([[-1], np.where(border, first[text[1:]] - 1, left[:-1])])
        after = np.concatenate([np.where(border, first[text[:-1] + 1] + 1, right[1:]), [n + 1]])
        head = np.concatenate([[True], border | (name[1:] != name[:-1])])
        at = np.flatnonzero(head)
        size = np.diff(np.append(at, len(name)))
        end = at + size - 1
        run = name[at]
        name = np.where(size > 1, pair(run, size.astype(np.uint64), 2 * r + 1), run)
        left, right, lo, text = before[at], after[end], lo[at], text[at]
        # pairs
        coin = (mix(name ^ np.uint64(r + 77)) & np.uint64(1)).astype(bool)
        border = text[1:] != text[:-1]
        before = np.concatenate([[-1], np.where(border, first[text[1:]] - 1, left[:-1])])
        after = np.concatenate([np.where(border, first[text[:-1] + 1] + 1, right[1:]), [n + 1]])
        joins = np.append(~coin[:-1] & coin[1:] & ~border, False)
        second = np.concatenate([[False], joins[:-1]])
        alone = ~joins & ~second
        mate = np.append(np.arange(1, len(name)), len(name) - 1)
        left = np.where(alone & coin, before, left)
        right = np.where(joins, right[mate], np.where(alone & ~coin, after, right))
        name = np.where(joins, pair(name, name[mate], 2 * r + 2), name)
        stay = ~second
        name, lo, left, right, text = name[stay], lo[stay], left[stay], right[stay], text[stay]
    return name, lo, left, right


def _least(name: np.ndarray, i: np.ndarray, j: np.ndarray) -> np.ndarray:
    """Index of the least name in each range [i, j), the first of equals; ranges must not be empty."""
    length = j - i
    out = np.empty(len(i), np.int64)
    table, span = np.arange(len(name)), 1
    todo = np.frexp(length)[1] - 1  # floor of log2
    for level in range(int(todo.max(initial=0)) + 1):
        if level:
            a, b = table[: len(table) - span], table[span:]
            table, span = np.where(name[a] <= name[b], a, b), 2 * span
        now = np.flatnonzero(todo == level)
        a, b = table[i[now]], table[j[now] - span]
        out[now] = np.where(name[a] <= name[b], a, b)
    return out


def file_windows(data: np.ndarray, offs: np.ndarray, window: int = WINDOW):
    """Rows of consecutive windows filed under one symbol: text, name, place of the symbol in the first window, first window
    (a word number in its text), how many, and the 40-bit contents of all of them end to end. Of windows under their own
    name that occur twice or more here, one is filed; all of them are settled, and come apart: text, first and last window
    of each stretch."""
    starts, ends, first = common.spans(data, offs)
    x = word_names(data, starts, ends)
    count = np.maximum(np.diff(first) - window + 1, 0)
    text, k = lists_of(count)
    s = first[text] + k
    if not len(s):
        return None
    name, lo, left, right = parse(x, first)
    n = len(x)
    i = np.concatenate([[0], np.cumsum(np.bincount(np.maximum(left, -1) + 1, minlength=n + 3))])[s + 1]  # symbols with left < s
    j = np.cumsum(np.bincount(np.minimum(right, n + 1), minlength=n + 3))[s + window]
    content = grams(x, window)[s]
    found = i < j
    anchor = -1 - np.arange(len(s))
    anchor[found] = _least(name, i[found], j[found])
    own = np.flatnonzero(~found)
    _, least, back, times = np.unique(content[own], return_index=True, return_inverse=True, return_counts=True)
    again = own[times[back] > 1]
    gap = np.flatnonzero((np.diff(s[again]) != 1) | (np.diff(text[again]) != 0))
    at, to = again[np.concatenate([[0], gap + 1])[: len(again)]], again[np.append(gap, len(again) - 1)[: len(again)]]
    settled = text[at], k[at], k[to]
    if len(again):
        stay = np.ones(len(s), bool)
        stay[again] = False
        stay[own[least]] = True
        text, k, s, content, found, anchor = (v[stay] for v in (text, k, s, content, found, anchor))
    head = np.flatnonzero(np.concatenate([[True], (anchor[1:] != anchor[:-1]) | (text[1:] != text[:-1])]))
    at, sure = anchor[head], found[head]
    where = np.where(sure, lo[np.maximum(at, 0)] - s[head], 0)
    filed = np.where(sure, name[np.maximum(at, 0)], pair(content[head], content[head], 99))
    return text[head], filed.view(np.int64), where, k[head], np.diff(np.append(head, len(s))), content.view(np.uint8).reshape(-1, 8)[:, :5], settled


@tidy
def _file(batches):
    for batch in batches:
        for a, b in slices(batch.column("text"), 1 << 20):
            part = batch.slice(a, b - a)
            got = file_windows(*text_buffer(part.column("text")))
            if got is None:
                continue
            text, name, lead, first, many, body, settled = got
            ends = np.concatenate([[0], np.cumsum(many * 5)]).astype(np.int32)
            if len(settled[0]):  # under names that meet nothing; lead tells them, body holds the last window
                who, a, b = settled
                last = b.astype("<i8").view(np.uint8).reshape(-1, 8)
                text, lead, first = np.concatenate([text, who]), np.concatenate([lead, np.full(len(who), SETTLED)]), np.concatenate([first, a])
                name = np.concatenate([name, mix(pair(a.astype(np.uint64), who.astype(np.uint64), 3)).view(np.int64)])
                ends = np.concatenate([ends, ends[-1] + 8 * np.arange(1, len(who) + 1)]).astype(np.int32)
                body = np.concatenate([np.ascontiguousarray(body).ravel(), last.ravel()])
            take = pa.array(text)
            yield pa.RecordBatch.from_arrays(
                [
                    pa.array(name), part.column("doc_id").take(take), part.column("th").take(take), pa.array(lead.astype(np.int32)), pa.array(first.astype(np.int32)),
                    pa.Array.from_buffers(pa.binary(), len(name), [None, pa.py_buffer(ends.tobytes()), pa.py_buffer(np.ascontiguousarray(body).tobytes())]),
                ],
                ["name", "doc_id", "th", "lead", "first", "body"],
            )


def _windows(table: pa.RecordBatch):
    """Of filed rows: the row of each window, the symbol's place in it, its first word, and its content as a number."""
    _, offsets, data = table.column("body").buffers()
    c = table.column("body")
    offs = np.frombuffer(offsets, np.int32)[c.offset : c.offset + len(c) + 1].astype(np.int64)
    raw = np.frombuffer(data, np.uint8)[offs[0] : offs[-1]].reshape(-1, 5).astype(np.int64)
    row, k = lists_of(np.diff(offs) // 5)
    content = raw @ (np.int64(256) ** np.arange(5))
    lead, first = table.column("lead").to_numpy(), table.column("first").to_numpy()
    return row, lead[row] - k, first[row] + k, content


def _spans(table: pa.RecordBatch, window: int = WINDOW) -> list[pa.RecordBatch]:
    """Rows with whole names, sorted by name: spans of words covered by windows that occur twice or more."""
    lead = table.column("lead").to_numpy()
    ready = None
    if (lead == SETTLED).any():
        mark = table.filter(pa.array(lead == SETTLED))
        last = np.frombuffer(b"".join(mark.column("body").to_pylist()), "<i8")
        ready = pa.RecordBatch.from_arrays([mark.column("doc_id"), mark.column("th"), mark.column("first"), pa.array((last + window).astype(np.int32))], ["doc_id", "th", "a", "b"])
        table = table.filter(pa.array(lead != SETTLED))
    return [x for x in (ready, _grouped(table, window) if table.num_rows else None) if x is not None]


def _grouped(table: pa.RecordBatch, window: int) -> pa.RecordBatch | None:
    name = table.column("name").to_numpy()
    group = np.cumsum(np.concatenate([[0], name[1:] != name[:-1]]))
    shared = np.flatnonzero(np.bincount(group)[group] > 1)
    if not len(shared):
        return None
    table, group = table.take(pa.array(shared)), group[shared]
    row, lead, first, content = _windows(table)
    key = group[row] * 64 + lead
    order = np.lexsort((content, key))
    same = (key[order][1:] == key[order][:-1]) & (content[order][1:] == content[order][:-1])
    twice = np.zeros(len(order), bool)
    twice[order[1:][same]] = True
    twice[order[:-1][same]] = True
    hit = np.flatnonzero(twice)
    if not len(hit):
        return None
    gap = (row[hit][1:] != row[hit][:-1]) | (first[hit][1:] != first[hit][:-1] + 1)
    at, to = hit[np.concatenate([[True], gap])], hit[np.concatenate([gap, [True]])]
    take = pa.array(row[at])
    return pa.RecordBatch.from_arrays(
        [table.column("doc_id").take(take), table.column("th").take(take), pa.array(first[at].astype(np.int32)), pa.array((first[to] + window).astype(np.int32))],
        ["doc_id", "th", "a", "b"],
    )


@tidy
def _settle(batches):
    """Streams a partition sorted by name; only the last, maybe unfinished, name waits for the next batch."""
    rest: list[pa.RecordBatch] = []
    for batch in batches:
        if not batch.num_rows:
            continue
        name = batch.column("name").to_numpy()
        cut = int(np.searchsorted(name, name[-1], "left"))
        if cut:
            whole = pa.Table.from_batches([*rest, batch.slice(0, cut)]).combine_chunks().to_batches()
            rest = []
            for part in whole:
                yield from _spans(part)
        rest.append(batch.slice(cut))
    if rest:
        for part in pa.Table.from_batches(rest).combine_chunks().to_batches():
            yield from _spans(part)


@tidy
def _loose(batches):
    """A row for each window of filed rows."""
    for batch in batches:
        batch = batch.filter(pa.array(batch.column("lead").to_numpy() != SETTLED))
        row, lead, first, content = _windows(batch)
        take = pa.array(row)
        yield pa.RecordBatch.from_arrays(
            [batch.column("name").take(take), pa.array(lead.astype(np.int32)), pa.array(content), batch.column("doc_id").take(take), batch.column("th").take(take), pa.array(first.astype(np.int32))],
            ["name", "lead", "content", "doc_id", "th", "a"],
        )


def repeated_spans(texts: DataFrame, hot: int = HOT) -> DataFrame:
    """texts: doc_id, th, text. Returns word spans [a, b) of each text that repeated windows cover; spans may overlap."""
    filed = texts.mapInArrow(_file, FILED)
    # which names are often is only looked up in a part of the rows: either path settles a name wholly and alike
    part = max(1, min(HOT_PART, hot // 5_000))
    some = filed if part == 1 else texts.where(F.rand(5) < 1 / part).mapInArrow(_file, FILED)
    often = common.cut(some.where(F.col("lead") != SETTLED).groupBy("name").agg(F.count("*").alias("n")).where(F.col("n") > hot // part).select("name"))
    n_hot = often.count()
    cold = filed
    if n_hot:
        often = F.broadcast(often) if n_hot <= HOT_BROADCAST else often
        cold = filed.join(often, "name", "left_anti")
    out = cold.repartition(F.col("name")).sortWithinPartitions("name").mapInArrow(_settle, SPAN)
    if n_hot:
        loose = common.cut(filed.where(F.col("lead") != SETTLED).join(often, "name", "left_semi").mapInArrow(_loose, "name long, lead int, content long, doc_id long, th long, a int"))
        key = ["name", "lead", "content"]
        twice = loose.groupBy(*key).agg(F.count("*").alias("n")).where("n > 1").select(*key)
        out = out.unionByName(loose.join(twice, key).select("doc_id", "th", "a", (F.col("a") + WINDOW).alias("b")))
    return out


def _with_spans(docs: DataFrame, th: str, cover: str, hot: int) -> DataFrame:
    """docs with the text's hash and the list of its covered spans; one exchange of the texts."""
    texts = docs.select("doc_id", "text", F.xxhash64("text").alias("th"))
    spans = repeated_spans(texts, hot).groupBy("doc_id", "th").agg(F.collect_list(F.struct("a", "b")).alias(cover))
    spans = spans.select(F.col("doc_id").alias("_d"), F.col("th").alias("_t"), cover)
    marked = docs.withColumn(th, F.xxhash64("text"))
    return marked.join(spans, marked["doc_id"].eqNullSafe(spans["_d"]) & (marked[th] == spans["_t"]), "left").drop("_d", "_t")


def _covered(spans: list[dict], n: int) -> np.ndarray:
    edge = np.zeros(n + 1, np.int64)
    for s in spans:
        edge[s["a"]] += 1
        edge[s["b"]] -= 1
    return np.cumsum(edge[:n]) > 0


@tidy
def _digest(batches):
    for batch in batches:
        rows = []
        for text, spans in zip(batch.column("text").to_pylist(), batch.column("cover").to_pylist()):
            words = (text or "").encode().split()
            n = len(words)
            if spans:
                gone = _covered(spans, n)
                words = [w for w, g in zip(words, gone.tolist()) if not g]
            rows.append((n, n - len(words), hashlib.sha256(b" ".join(words)).hexdigest()))
        n, gone, sha = zip(*rows) if rows else ((), (), ())
        yield pa.RecordBatch.from_arrays([batch.column("doc_id"), pa.array(n, pa.int64()), pa.array(gone, pa.int64()), pa.array(sha, pa.string())], ["doc_id", "n_words", "n_removed", "kept_sha256"])


def digests(docs: DataFrame, hot: int = HOT) -> DataFrame:
    """Per document: doc_id, n_words, n_removed and the hash of the kept words joined by blanks."""
    marked = _with_spans(docs.select("doc_id", "text"), "th", "cover", hot).select("doc_id", "text", "cover")
    return marked.mapInArrow(_digest, "doc_id long, n_words long, n_removed long, kept_sha256 string")


def cut_words(text: str, spans: list[dict]) -> str:
    """The text without the covered words; each goes with the blanks behind it, the rest stays as it is."""
    raw = text.encode()
    data = np.frombuffer(raw, np.uint8)
    starts, _, _ = common.spans(data, np.array([0, len(data)]))
    gone = _covered(spans, len(starts))
    edge = np.append(starts, len(raw))
    lead = [raw[: edge[0]]]
    return b"".join(lead + [raw[edge[i] : edge[i + 1]] for i in np.flatnonzero(~gone)]).decode()


def remove_repeats(docs: DataFrame, hot: int = HOT) -> DataFrame:
    """The documents with their repeated passages cut out of text (and n_chars, if there, set anew); a document of which
    no word is left goes. All other columns stay."""
    names = {c.lower() for c in docs.columns}
    th, cover = (next(x for x in (f"{base}{'_' * i}" for i in range(len(names) + 1)) if x not in names) for base in ("_th", "_cover"))
    schema, columns = docs.schema, docs.columns

    def apply(batches):
        for batch in batches:
            old, spans = batch.column("text").to_pylist(), batch.column(cover).to_pylist()
            new = [cut_words(t, s) if s else t for t, s in zip(old, spans)]
            keep = pa.array([not s or bool(t.encode().split()) for t, s in zip(new, spans)], pa.bool_())
            batch = batch.set_column(batch.schema.get_field_index("text"), "text", pa.array(new, pa.string()))
            if "n_chars" in columns:
                at = batch.schema.get_field_index("n_chars")
                kind = batch.schema.field(at).type
                size = [len(t) if s else c for t, s, c in zip(new, spans, batch.column("n_chars").to_pylist())]
                batch = batch.set_column(at, "n_chars", pa.array(size, kind))
            yield batch.filter(keep).select(columns)

    return _with_spans(docs, th, cover, hot).mapInArrow(tidy(apply), schema)
