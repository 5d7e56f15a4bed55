"""Each training-data operator against a brute-force version, and on nulls, blanks, long texts, ties, repeats, no rows and
columns of clashing names."""

import base64
import collections
import hashlib
import json
import random
import re
import zlib

import numpy as np
import public_tokenizers
import pyarrow as pa
import pytest
import tiktoken
import xxhash
from hypothesis import given, settings
from hypothesis import strategies as st
from pyspark.sql import functions as F
from tokenizers import Tokenizer

from graphstitch.llm import bpe_tree, language_gru, license_rules, order_minhash, quality_llr, rans, recompression, toxicity_knn, warc, winnowing

random.seed(5)
TERM = re.compile("[^\x00-\x2f\x3a-\x60\x7b-\x7f]+")
ASCII = str.maketrans("ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")
VOCAB = ["the", "of", "and", "été", "größe", "niño", "x1", "Apache", "license,", "MIT", "it's", "ÉCOLE", "run", "alpha", "beta"]


def words(n):
    return " ".join(random.choice(VOCAB) + (str(random.randint(0, 400)) if random.random() < 0.5 else "") for _ in range(n))


PASSAGE, ITEM = words(60), words(20)
TEXTS = [
    None, "", "   \n\t ", "one", "a b c d e f", words(12), words(300), words(300), PASSAGE + " " + words(40), words(30) + "\n" + PASSAGE, words(9) + " " + PASSAGE[: len(PASSAGE) // 2],
    "same " * 200, "a b " * 90, words(3000), "w" * 5000, "line one two\nline one two\nother\n\n", words(50) + " " + ITEM.upper().replace("É", "É") + " " + words(20),
    "GNU General Public License v3 or later; licensed under the MIT License. cc by cc by-sa 4.0", "#*$ 10% & <b> | x", "<|endoftext|> tail", "日本語 テキスト 123",
]
ROWS = [(i, t) for i, t in enumerate(TEXTS)] + [(6, TEXTS[6]), (100, TEXTS[6]), (101, TEXTS[7] + " tail"), (None, TEXTS[13]), (None, None), (7, "other text under a used id")]
CLASHES = ["w", "h", "th", "cover", "score", "kept", "n_words", "_row", "sk", "key"]


@pytest.fixture(scope="module")
def docs(spark):
    df = spark.createDataFrame([(i, t, "en", "s", len(t or "")) for i, t in ROWS], "doc_id long, text string, lang string, source string, n_chars long")
    return df.withColumns({c: F.lit(1) for c in CLASHES}).repartition(3)


@pytest.fixture(scope="module")
def none(spark, docs):
    return docs.limit(0)


@pytest.fixture(scope="module")
def labels(spark):
    return spark.createDataFrame([(5, 1, 0), (6, 1, 0), (6, 1, 1), (7, 1, 0), (11, 0, 0), (None, 1, 1), (3, None, None)], "doc_id long, quality int, toxic int")


def rows(df, *cols):
    return sorted((tuple(r[c] for c in cols) for r in df.collect()), key=str)


# --- 1 ------------------------------------------------------------------------------------------------------------------------
def test_warc(spark):
    pages = [(1, "http://a/1", "<p>x\r\n\r\ny</p>"), (2, "http://a/2", "<p>x\r\n\r\ny</p>"), (3, None, None), (4, "u\r\nX: y", ""), (5, "http://a/5", "é" * 9000), (9, "http://a/9", "<p>x\r\n\r\ny</p>"), (9, "http://a/9", "<p>x\r\n\r\ny</p>"), (None, "http://n", "<p>x\r\n\r\ny</p>")]
    # payloads that end or begin like the line ends around them, and one larger than a reader's buffers
    pages += [(20 + i, f"http://e/{i}", x) for i, x in enumerate(["a\r\n", "\r\n\r\n", "\r", "b\r\n\r", "\r\n\r\r\n\r\nc", "WARC/1.1\r\n\r\n", "z\r\n\r" * 40_000, "q" * 3_000_000])]
    df = spark.createDataFrame(pages, "page_id long, url string, html string").withColumn("digest", F.lit(0))
    got = rows(warc.round_trip(df), "page_id", "payload_bytes", "payload_digest", "record_type", "refers_to")
    best = {}
    for i, _, h in pages:
        best[h or ""] = max(best.get(h or "", -1), -1 if i is None else i)
    want = []
    for i, _, h in pages:
        raw = (h or "").encode()
        first = i == best[h or ""]
        want.append((i, len(raw), base64.b32encode(hashlib.sha1(raw).digest()).decode(), "response" if first else "revisit", None if first else best[h or ""]))
    assert got == sorted(want, key=str)
    assert warc.round_trip(df.limit(0)).isEmpty()
    assert {r["record_type"] for r in warc.round_trip(df, least_bytes=10**6).collect()} == {"response"}
    with pytest.raises(ValueError):
        list(warc.parse(b"WARC/1.1\r\nContent-Length: 5\r\n\r\nab\r\n\r\n"))


# --- 2 ------------------------------------------------------------------------------------------------------------------------
def test_nearest_neighbours_are_exact():
    rng = random.Random(2)
    examples = sorted({tuple(sorted({(rng.randrange(12), rng.randint(1, 3)) for _ in range(rng.randint(1, 5))}, key=lambda x: x[0])) for _ in range(150)})
    examples = [tuple({t: n for t, n in e}.items()) for e in examples]
    index = toxicity_knn.Index(np.linspace(1, 3, 12), [(e, 1, i % 2, i) for i, e in enumerate(sorted(set(examples)))], 0.1, block=8)
    order = sorted(set(examples))
    for q in order[:40]:
        t, w = index.weights(q)
        dense = np.zeros(12)
        dense[t] = w
        brute = []
        for i, e in enumerate(order):
            te, we = index.weights(e)
            brute.append((float(dense[te] @ we), i))
        brute = sorted((s for s, _ in brute if s > 0), reverse=True)[:15]
        assert np.allclose([s for s, _ in index.nearest(q)], brute)


def test_toxicity(spark, none, labels):
    rng = random.Random(3)
    data = []
    for i in range(600):
        bad = i % 5 == 0
        body = [rng.choice("lorem ipsum dolor sit amet consetetur sed diam".split()) for _ in range(40)]
        data.append((i, " ".join(body + ["Vilest", "WORM"][: 1 + i % 2] * bad), int(bad)))
    df = spark.createDataFrame([(i, t) for i, t, _ in data] + [(900, None), (901, ""), (None, "vilest worm")], "doc_id long, text string").withColumn("score", F.lit(0))
    lb = spark.createDataFrame([(i, y) for i, _, y in data] + [(5, None)], "doc_id long, toxic int")
    got = {r["doc_id"]: r for r in toxicity_knn.score(df, lb).collect()}
    assert len(got) == 603 and all(0 <= r["score"] <= 1 and r["predicted"] == int(r["score"] >= 0.7) for r in got.values())
    assert all(got[i]["predicted"] == y for i, _, y in data) and got[None]["predicted"] == 1 and got[900]["predicted"] == 0
    assert all(got[i]["held_out"] == (zlib.crc32(str(i).encode()) % 3 == 1) for i, _, _ in data)
    assert toxicity_knn.score(df.limit(0), lb).isEmpty()
    assert {r["score"] for r in toxicity_knn.score(df, lb.limit(0)).collect()} == {0.0}


def test_toxicity_query_against_brute_force(spark):
    """Neighbours and votes of whole documents by dense cosines over the fitted terms; long text, ties and repeats."""
    rng = random.Random(12)
    bad_words = "vilest worm wretch cur".split()
    data = []
    for i in range(300):
        body = [rng.choice("lorem ipsum dolor sit amet".split()) for _ in range(20)]
        data.append((i, " ".join(body + rng.choices(bad_words, k=rng.randint(1, 3)) * (i % 4 == 0)), int(i % 4 == 0)))
    data += [(1000, "vilest worm " * 50_000, 1), (1001, data[0][1], 1), (1001, data[0][1], 1)]
    df = spark.createDataFrame([x[:2] for x in data], "doc_id long, text string")
    vocabulary, index = toxicity_knn.fit(df, spark.createDataFrame([(i, y) for i, _, y in data], "doc_id long, toxic int"))
    assert set(vocabulary) == {w.encode() for w in bad_words}
    got = toxicity_knn.score(df, spark.createDataFrame([(i, y) for i, _, y in data], "doc_id long, toxic int")).collect()
    learned = [(toxicity_knn.vector(t, vocabulary), y) for i, t, y in dict((x[0], x) for x in data).values() if zlib.crc32(str(i).encode()) % 3 != 1]
    learned += [learned[-1]] * (zlib.crc32(b"1001") % 3 != 1)

    def dense(v):
        out = np.zeros(len(vocabulary))
        if v:
            at, w = index.weights(v)
            out[at] = w
        return out

    for r in rng.sample(got, 60) + [r for r in got if r["doc_id"] in (1000, 1001)]:
        text = next(t for i, t, _ in data if i == r["doc_id"])
        v = toxicity_knn.vector(text, vocabulary)
        if not v:
            assert abs(r["score"] - index.base) < 1e-9
            continue
        near = sorted(((float(dense(v) @ dense(e)), e) for e in {e for e, _ in learned if e}), key=lambda x: (-x[0], x[1]))[: toxicity_knn.NEIGHBOURS]
        left, up, down = toxicity_knn.NEIGHBOURS, toxicity_knn.SHRINK * index.base, toxicity_knn.SHRINK
        for cos, e in near:
            ys = [y for x, y in learned if x == e]
            n = min(left, len(ys))
            up, down, left = up + cos**2 * n * sum(ys) / len(ys), down + cos**2 * n, left - n
            if cos <= 0 or left <= 0:
                break
        a, b = index.curve
        assert abs(r["score"] - 1 / (1 + np.exp(-(a * index._odds(up / down) + b)))) < 1e-6, r


def test_toxic_terms_of_a_small_sample(spark):
    data = [(i, " ".join(["lorem ipsum dolor"] + ["vilest worm"] * (i % 5 == 0)), int(i % 5 == 0)) for i in range(80)]
    df = spark.createDataFrame([x[:2] for x in data], "doc_id long, text string")
    got = toxicity_knn.score(df, spark.createDataFrame([(i, y) for i, _, y in data], "doc_id long, toxic int")).collect()
    assert {r["doc_id"]: r["predicted"] for r in got} == {i: y for i, _, y in data}


def test_toxicity_learns_from_all_labels(spark):
    """36,000 labels, two thirds of them to learn from: none is passed over, and votes taken in tasks give the same curve."""
    text = F.concat(F.lit("lorem ipsum "), F.when(F.col("id") % 4 == 0, F.concat(F.lit("vilest "), F.repeat(F.lit("worm "), (F.col("id") % 7).cast("int")))).otherwise(""))
    df = spark.range(36_000).select(F.col("id").alias("doc_id"), text.alias("text"))
    lb = spark.range(36_000).select(F.col("id").alias("doc_id"), (F.col("id") % 4 == 0).cast("int").alias("toxic"))
    vocabulary, index = toxicity_knn.fit(df, lb)
    want = [i for i in range(0, 36_000, 4) if zlib.crc32(str(i).encode()) % 3 != 1]
    assert set(vocabulary) == {b"vilest", b"worm"} and index.many.sum() == index.toxic.sum() == len(want)
    vectors = sorted({toxicity_knn.vector("vilest " + "worm " * k, vocabulary) for k in range(7)})
    again = toxicity_knn.Index(index.idf, [(v, int(n), int(a), i) for v, n, a, i in zip(vectors, index.many, index.toxic, index.ids)], index.base)
    assert np.allclose(index.curve, again.curve, atol=1e-9)


# --- 3 ------------------------------------------------------------------------------------------------------------------------
def test_license(docs, none):
    want = []
    for i, t in ROWS:
        w = TERM.findall((t or "").translate(ASCII))
        at, found = [], set()
        for phrase, label in license_rules.BASE.items():
            p = phrase.split()
            here = [k for k in range(len(w)) if w[k : k + len(p)] == p]
            at += here
            found |= {label} if here else set()
        want.append((i, len(w), len(at), min(at, default=None), max(at, default=None), ",".join(sorted(found))))
    out = license_rules.scan(docs)
    assert rows(out, "doc_id", "n_words", "n_base", "first_word", "last_word", "base_labels") == sorted(want, key=str)
    assert all(set(r["base_labels"].split(",")) - {""} <= set(r["labels"].split(",")) and 0 <= r["score"] <= 1 for r in out.collect())
    assert license_rules.scan(none).isEmpty()


def test_license_rules_overlap():
    s = license_rules.scanner()
    assert len(license_rules.rules()) > 250
    assert s.scan("Under the GNU Lesser General Public License, version 2.1 or later")[5] == "lgpl-2-1-or-later"
    assert s.scan("SPDX-License-Identifier: MPL-2.0")[5] == "mpl-2-0"
    assert s.scan("CC BY-NC-SA 4.0")[4:6] == ("cc-by", "cc-by,cc-by-nc-sa-4-0")


def examples(expression):
    """Texts that an expression matches: every alternative, optional parts there and not."""
    import re._parser as parser

    def texts(part):
        out = [""]
        for op, x in part:
            op = str(op)
            if op == "LITERAL":
                more = [chr(x)]
            elif op == "IN":
                more = [next(chr(y) if str(k) == "LITERAL" else "1" for k, y in x)]
            elif op == "SUBPATTERN":
                more = texts(x[3])
            elif op == "BRANCH":
                more = [y for z in x[1] for y in texts(z)]
            elif op == "MAX_REPEAT":
                more = [y * max(1, x[0]) for y in texts(x[2])] + [""] * (x[0] == 0)
            else:
                more = [""]
            out = [a + b for a in out for b in more][:300]
        return out

    return texts(parser.parse(expression))


def test_license_gate_lets_every_rule_through():
    s = license_rules.scanner()
    for r in license_rules.rules():
        for text in examples(r.pattern.decode().replace("\\S", "x")):
            text = f" {text.strip()} ".encode()
            if re.search(r.pattern, text):
                assert s.opens(text) and r.keyword in text, (r, text)
    for text, label in [("released under the wtfpl", "wtfpl"), ("wtfpl version 2", "wtfpl-2"), ("GPLv2 or later", "gpl-2-or-later"), ("SPDX-License-Identifier: GPL-2.0-or-later", "gpl-2-0-or-later"), ("gpl v3 only", "gpl-3-only")]:
        assert s.scan(text)[5] == label


def test_license_long_text_and_ties(spark):
    text = "licensed under the MIT License, " * 20_000
    got = license_rules.scan(spark.createDataFrame([(1, text), (1, text), (2, "mit license apache license")], "doc_id long, text string")).collect()
    assert [r["n_base"] for r in got if r["doc_id"] == 1] == [20_000] * 2 and {r["labels"] for r in got} == {"mit", "apache,mit"}


# --- 4 ------------------------------------------------------------------------------------------------------------------------
@settings(max_examples=30, deadline=None)
@given(st.lists(st.integers(0, 300), max_size=700), st.integers(1, 40))
def test_rans_blocks(ids, lanes):
    ids = np.array(ids, np.uint32)
    table = rans.Table(np.bincount(ids, minlength=301), 12)
    sizes = np.array([len(ids) // 2, len(ids) - len(ids) // 2])
    block = rans.encode_block(ids, [7, None], sizes, table, lanes)
    docs, got, back = rans.decode_block(block, table)
    assert docs == [7, None] and got.tolist() == sizes.tolist() and back.tolist() == ids.tolist()
    steps, every = -(-len(ids) // lanes), rans.CHECK_STEPS
    parts = [rans.decode_block(block, table, k, k + 1)[2] for k in range(-(-steps // every))]
    assert np.concatenate([*parts, np.empty(0, np.uint32)])[: len(ids)].tolist() == ids.tolist()
    if len(ids) > 50:
        broken = bytearray(block)
        broken[-1] ^= 1
        with pytest.raises(ValueError):
            if rans.decode_block(bytes(broken), table)[2].tolist() == ids.tolist():
                raise ValueError("unused word")


def test_ids_file(docs, none):
    tk = Tokenizer.from_file(public_tokenizers.path(rans.TOKENIZER))
    out = rows(rans.round_trip(docs), "doc_id", "start", "n_tokens", "ids_crc32")
    encoded = [(i, [*tk.encode(t or "", add_special_tokens=False).ids, 1]) for i, t in ROWS]
    assert sorted(((i, n, c) for i, _, n, c in out), key=str) == sorted(((i, len(e), zlib.crc32(np.array(e, "<u4").tobytes())) for i, e in encoded), key=str)
    ordered = sorted(out, key=lambda r: r[1])
    assert [r[1] for r in ordered] == np.cumsum([0, *(r[2] for r in ordered)])[:-1].tolist()
    assert [r[0] for r in ordered] == sorted((r[0] for r in out), key=lambda d: (d is not None, d or 0))
    assert rans.round_trip(none).isEmpty()


# --- 5 ------------------------------------------------------------------------------------------------------------------------
def test_gradients():
    net = language_gru.Network(["a", "b", "c"], hidden=3)
    net.w = {k: v.astype(np.float64) for k, v in net.w.items()}
    rng = np.random.default_rng(1)
    data, label = rng.integers(60, 66, (5, 7)).astype(np.uint8), np.array([0, 1, 2, 0, 1])
    _, g = net.gradients(data, label)
    for k in net.w:
        flat, at = net.w[k].reshape(-1), int(np.argmax(np.abs(g[k])))
        keep = flat[at]
        flat[at] = keep + 1e-2
        up = net.gradients(data, label)[0]
        flat[at] = keep - 1e-2
        down = net.gradients(data, label)[0]
        flat[at] = keep
        assert abs((up - down) / 2e-2 - g[k].reshape(-1)[at]) < 2e-2 * max(1, abs(g[k].reshape(-1)[at]))


def test_language(spark):
    rng = random.Random(4)
    pools = {"xx": "zorb quix vlad kroz".split(), "yy": "amé olé bené caté".split()}
    data = [(i, " ".join(rng.choice(pools["xx" if i % 2 else "yy"]) for _ in range(rng.randint(6, 60))), "xx" if i % 2 else "yy") for i in range(200)]
    df = spark.createDataFrame([*data, (900, None, "xx"), (901, "", None), (902, "12 34 !", "yy"), (None, "zorb quix vlad zorb", None)], "doc_id long, text string, lang string")
    got = {r["doc_id"]: r for r in language_gru.identify(df).collect()}
    held = [(i, y) for i, _, y in data if zlib.crc32(str(i).encode()) % 5 == 0]
    assert sum(got[i]["lang_pred"] == y for i, y in held) >= 0.95 * len(held) and all(got[i]["held_out"] for i, _ in held)
    assert [(got[i]["lang_pred"], got[i]["score"]) for i in (900, 901, 902)] == [("und", 0.0)] * 3
    assert language_gru.identify(df.limit(0)).isEmpty()


# --- 6 ------------------------------------------------------------------------------------------------------------------------
def kept_words(all_rows, window=recompression.WINDOW):
    split = [(i, (t or "").encode().split()) for i, t in all_rows]
    seen = collections.Counter(tuple(w[k : k + window]) for _, w in split for k in range(len(w) - window + 1))
    out = []
    for i, w in split:
        gone = [False] * len(w)
        for k in range(len(w) - window + 1):
            if seen[tuple(w[k : k + window])] > 1:
                gone[k : k + window] = [True] * window
        out.append((i, w, gone))
    return out


@pytest.mark.parametrize("hot", [100_000, 3])
def test_repeats(docs, none, hot):
    want = []
    for i, w, gone in kept_words(ROWS):
        kept = [x for x, g in zip(w, gone) if not g]
        want.append((i, len(w), len(w) - len(kept), hashlib.sha256(b" ".join(kept)).hexdigest()))
    assert rows(recompression.digests(docs, hot), "doc_id", "n_words", "n_removed", "kept_sha256") == sorted(want, key=str)
    assert recompression.digests(none, hot).isEmpty()


def test_remove_repeats(docs):
    out = recompression.remove_repeats(docs)
    assert out.columns == docs.columns
    want = [(i, [x.decode() for x, g in zip(w, gone) if not g]) for i, w, gone in kept_words(ROWS) if not any(gone) or not all(gone)]
    assert sorted(((r["doc_id"], [w.decode() for w in (r["text"] or "").encode().split()]) for r in out.collect()), key=str) == sorted(want, key=str)


# --- 7 ------------------------------------------------------------------------------------------------------------------------
@pytest.fixture(scope="module")
def reference():
    return tiktoken.Encoding("own", pat_str=public_tokenizers.PATTERN, mergeable_ranks=bpe_tree.load_ranks(public_tokenizers.path(bpe_tree.RANKS)), special_tokens={})


def test_bpe(docs, none, reference):
    want = []
    for i, t in ROWS:
        ids = reference.encode_ordinary(t or "")
        want.append((i, len(ids), hashlib.sha256(",".join(map(str, ids)).encode()).hexdigest(), hashlib.sha256((t or "").encode()).hexdigest()))
    assert rows(bpe_tree.digests(docs), "doc_id", "n_tokens", "ids_sha256", "decoded_sha256") == sorted(want, key=str)
    assert rows(bpe_tree.tokens(docs), "doc_id", "ids") == sorted(((i, reference.encode_ordinary(t or "")) for i, t in ROWS), key=str)
    assert bpe_tree.digests(none).isEmpty()


@settings(max_examples=400, deadline=None)
@given(st.text(st.sampled_from(list(" \n\n  \t\r'aebcrtvs1é日!…\u00a0\u3000 ")), max_size=120), st.integers(1, 9))
def test_bpe_joins(reference, text, leaf):
    """Whatever the size of the leaves, the tree gives the library's ids and its bytes."""
    bpe = bpe_tree.encoder(public_tokenizers.path(bpe_tree.RANKS))
    raw = text.replace(" ", "").encode()
    old = bpe_tree.LEAF_CHARS, bpe_tree.LEAF_BYTES, bpe_tree.LEAF_IDS
    bpe_tree.LEAF_CHARS, bpe_tree.LEAF_BYTES, bpe_tree.LEAF_IDS = leaf, 1 + leaf % 4, leaf
    try:
        ids = np.frombuffer(bpe.encode(text), np.int32).tolist()
        assert ids == reference.encode_ordinary(text) and bpe.decode(ids) == text.encode()
        assert not raw or [bpe.bytes_of[i] for i in bpe.piece(raw)] == bpe.merge(raw)
    finally:
        bpe_tree.LEAF_CHARS, bpe_tree.LEAF_BYTES, bpe_tree.LEAF_IDS = old


# --- 8 ------------------------------------------------------------------------------------------------------------------------
def test_quality(docs, none, labels):
    want = []
    for i, t in ROWS:
        t = t or ""
        w = re.findall(r"[^\x20\x09-\x0D]+", t)
        five = collections.Counter(tuple(w[k : k + 5]) for k in range(len(w) - 4))
        again = {j for k in range(len(w) - 4) if five[tuple(w[k : k + 5])] > 1 for j in range(k, k + 5)}
        lines = [x for x in t.split("\n") if re.search(r"[^\x20\x09-\x0D]", x)]
        failed = len(w) < 10 or 100 * len(again) > 20 * len(w)
        want.append((i, len(w), sum(map(len, w)), sum(c in "#*$%&|<>" for c in t), len(lines) - len(set(lines)), len(again), failed))
    out = quality_llr.assess(docs, labels)
    assert rows(out, "doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed") == sorted(want, key=str)
    assert all(not r["kept"] for r in out.collect() if r["base_failed"])
    kept = quality_llr.keep_good(docs, labels)
    assert kept.columns == docs.columns and rows(kept, "doc_id", "text") == rows(out.where("kept"), "doc_id", "text")
    assert quality_llr.assess(none, labels).isEmpty() and quality_llr.assess(docs, labels.limit(0)).count() == len(ROWS)


def test_quality_separates(spark):
    rng = random.Random(6)
    good = [(i, " ".join(rng.choice(VOCAB) for _ in range(60)), 1) for i in range(200)]
    junk = [(1000 + i, " ".join(rng.choice("BUY!! NOW!! WIN!! $$$ click|here".split()) + str(rng.randint(0, 30)) for _ in range(60)), 0) for i in range(60)]
    df = spark.createDataFrame([(i, t) for i, t, _ in good + junk], "doc_id long, text string")
    lb = spark.createDataFrame([(i, q) for i, _, q in good[:120] + junk[:20]], "doc_id long, quality int")
    kept = {r["doc_id"] for r in quality_llr.assess(df, lb).where("score >= -0.08").collect()}
    assert kept == {i for i, _, _ in good}


def test_quality_scores(docs, labels):
    """Ratio and verdict against a version that counts n-grams in dictionaries, with the hash written out."""

    def name(*parts):
        seed = 42
        for w in parts:
            seed = xxhash.xxh64_intdigest(w.encode(), seed)
        return (seed - 2**64 if seed >= 2**63 else seed) % quality_llr.BUCKETS

    def grams(t):
        w = re.findall(r"[^\x20\x09-\x0D]+", t or "")
        return [name(x) for x in w] + [name(x, y) for x, y in zip(w, w[1:])]

    trusted = {r["doc_id"] for r in labels.collect() if r["quality"] == 1 and r["doc_id"] is not None}
    raw, good = collections.Counter(), collections.Counter()
    for i, t in ROWS:
        raw.update(grams(t))
        good.update(grams(t) if i in trusted else [])
    share = sum(good.values()) / sum(raw.values())
    ratio = {b: np.log((good[b] + quality_llr.PRIOR) / (n * share + quality_llr.PRIOR)) for b, n in raw.items()}
    want = sorted((str(i), round(float(np.mean([ratio[g] for g in grams(t)])) if grams(t) else 0.0, 9)) for i, t in ROWS)
    out = quality_llr.assess(docs, labels).collect()
    assert sorted((str(r["doc_id"]), round(r["score"], 9)) for r in out) == want
    assert all(r["kept"] == (not r["base_failed"] and r["score"] >= quality_llr.THRESHOLD) for r in out)


# --- 9 ------------------------------------------------------------------------------------------------------------------------
@settings(max_examples=300, deadline=None)
@given(st.lists(st.sampled_from("abc"), max_size=14), st.lists(st.sampled_from("abcd"), max_size=14), st.integers(0, 14))
def test_banded_distance(a, b, k):
    d = list(range(len(b) + 1))
    for i, x in enumerate(a):
        e = [i + 1]
        for j, y in enumerate(b):
            e.append(min(d[j + 1] + 1, e[j] + 1, d[j] + (x != y)))
        d = e
    assert order_minhash.distance_within(a, b, k) == (d[-1] if d[-1] <= k else None)


def test_leaves_of_a_text_share_the_remembered_words():
    """A leaf behind a sure place starts with a blank and is ordinary all the same; odd white space leaves words as they are."""
    path = public_tokenizers.path(bpe_tree.RANKS)
    ranks = bpe_tree.load_ranks(path)
    whole = tiktoken.Encoding("x", pat_str=public_tokenizers.PATTERN, mergeable_ranks=ranks, special_tokens={})
    bpe = bpe_tree.Bpe(ranks, public_tokenizers.PATTERN)
    one = words(3000)
    for text in (one, one.replace(" ", "\n", 40), " " + one, "\n" + one, "\n\n" + one, one + " ", one.replace(" ", "  ", 200), one.replace(" ", "\t", 9), " \n" + one + "\r\n" + one):
        assert np.frombuffer(bpe.encode(text), np.int32).tolist() == whole.encode_ordinary(text)
        if text is one:
            assert not bpe.odd.young
    assert len(bpe.odd.young) < 40


def test_known_runs_need_the_model_only():
    """Every character below U+0100, alone and in a run, as the library has it, with the model alone at work."""
    path = public_tokenizers.path(rans.TOKENIZER)
    whole, tokens = Tokenizer.from_file(path), rans.Tokens(path)
    every = [chr(i) for i in range(256)]
    texts = ["".join(every), " ".join(every), " ".join(f"a{c}b" for c in every), " ".join(f"{c}{c}it's 10%{c}" for c in every), words(2000), "x\n\ny", "\n", " \n ", "\x85 \xa0"]
    tokens.tokenizer = None
    got = [np.frombuffer(x, tokens.kind).tolist() for x in tokens.batch(texts)]
    assert got == [whole.encode(t, add_special_tokens=False).ids for t in texts]
    assert tokens.batch(["<|endoftext|"] * 2)[0] == tokens.batch(["<|endoftext|"])[0]


@pytest.mark.parametrize("most", [20, 300_000])
def test_ids_of_a_column(most):
    """All texts of a column at once: runs of any characters, special tokens (also begun in one text and ended in the next),
    apostrophes at every edge; a forgetful memory gives the same ids, and long pre-tokens are never held."""
    rng, path = random.Random(11), public_tokenizers.path(rans.TOKENIZER)
    whole, tokens = Tokenizer.from_file(path), rans.Tokens(path, most)
    atoms = [*map(chr, range(256)), *["'", "'s", "'RE", "'ll", "s", "re", " ", "\n", "it", "É", "e\u0301", "’s", "İ", "ΟΔΟΣ", "日本", "\u3000", "٣", "😀", "<|endoftext|>", "<|startoftext|>"] * 5]
    texts = [None, "", "a <|endof", "text|> b", "it'", "s", "'", "re", "é" * 300, "日本" * 300]
    for _ in range(60):
        column = texts + [None if rng.random() < 0.05 else "".join(rng.choices(atoms, k=rng.choice([1, 2, 5, 40]))) for _ in range(8)]
        ids, places = tokens.encode(pa.array(column).slice(1))
        want = [whole.encode(t or "", add_special_tokens=False).ids for t in column[1:]]
        assert [ids[x:y].tolist() for x, y in zip(places[:-1], places[1:])] == want
        assert len(tokens.keys) <= most and max(map(len, tokens.keys.to_pylist())) <= tokens.longest
    assert tokens.batch([]) == [] and tokens.batch([None, "", " \n"]) == [b""] * 3


def test_ids_by_other_tokenizers(tmp_path):
    """Where the settings are not those that are cut here, blanks may matter: the library gets whole texts."""
    form = json.loads(open(public_tokenizers.path(rans.TOKENIZER), encoding="utf-8").read())
    form["pre_tokenizer"] = {"type": "ByteLevel", "add_prefix_space": False, "trim_offsets": True, "use_regex": False}
    path = tmp_path / "other.json"
    path.write_text(json.dumps(form), encoding="utf-8")
    texts = ["one two  three", None, "a\nb c", ""]
    tokens, whole = rans.Tokens(str(path)), Tokenizer.from_file(str(path))
    assert [np.frombuffer(x, tokens.kind).tolist() for x in tokens.batch(texts)] == [whole.encode(t or "", add_special_tokens=False).ids for t in texts]


def test_near_copies(spark, docs, none):
    base = [words(random.randint(40, 200)) for _ in range(12)]
    data = []
    for g, t in enumerate(base):
        data.append((10 * g, t))
        for c in range(1, 4):
            w = t.split()
            w[random.randrange(len(w))] = "changed"
            data.append((10 * g + c, " ".join(w) if c < 3 else t))
    df = spark.createDataFrame(data, "doc_id long, text string").withColumn("h", F.lit(0)).repartition(4)
    got = {r["doc_id"]: r for r in order_minhash.membership(df).collect()}
    assert {i: r["class_id"] for i, r in got.items()} == {i: i - i % 10 for i, _ in data} and all(r["members"] == 4 for r in got.values())
    assert rows(order_minhash.keep_one(df), "doc_id") == sorted(((10 * g,) for g in range(12)), key=str)
    out = order_minhash.membership(docs)
    assert out.count() == len(ROWS)
    one = {(r["doc_id"], r["class_id"]) for r in out.collect()}
    assert {(0, 0), (1, 0), (100, 6), (101, 7)} <= one
    kept = order_minhash.keep_one(docs)
    assert kept.columns == docs.columns and kept.where("doc_id = 6").count() == 1
    assert order_minhash.membership(none).isEmpty() and order_minhash.keep_one(none).isEmpty()


def test_every_pair_of_a_bucket_is_settled(spark):
    """Near copies that share sketches only with many other texts, by way of a passage that all have."""
    rng = random.Random(8)
    shared = [f"s{i}" for i in range(100)]
    data = []
    for g in range(30):
        own = [f"w{rng.randrange(10**6)}" for _ in range(30)]
        copy = [f"c{rng.randrange(10**6)}" if x % 5 == 2 else w for x, w in enumerate(own)]
        data += [(2 * g, " ".join(shared + own)), (2 * g + 1, " ".join(shared + copy))]
    df = spark.createDataFrame(data, "doc_id long, text string").repartition(4)
    got = {r["doc_id"]: r["class_id"] for r in order_minhash.membership(df).collect()}
    assert got == {i: i - i % 2 for i, _ in data}


def test_pairs_of_a_bucket_are_not_joined_one_by_one(spark, monkeypatch):
    """A long passage that many texts share brings all of them close to the bound: joins with texts make rows by texts, not by pairs."""
    rng = random.Random(11)
    shared = [f"s{i}" for i in range(300)]
    data = [(i, " ".join(shared + [f"w{rng.randrange(90)}" for _ in range(88)])) for i in range(120)]
    data += [(200 + i, t.replace("s7 ", "changed ")) for i, t in data[:40]]
    made, cut = [], order_minhash.common.cut

    def counted(df):
        names = df.columns
        out = cut(df)
        made.append((names, out.count()))
        return out

    monkeypatch.setattr(order_minhash.common, "cut", counted)
    got = {r["doc_id"]: r["class_id"] for r in order_minhash.membership(spark.createDataFrame(data, "doc_id long, text string").repartition(4)).collect()}
    assert got == {i: i % 200 for i, _ in data}
    pairs = max(n for names, n in made if names == ["a", "b"])
    moved = [n for names, n in made if names == ["s", "h", "others"]]
    assert pairs > 2000 and moved and max(moved) < pairs / 5


def test_a_component_is_one_row_of_a_bucket(spark, monkeypatch):
    """Many near copies share many buckets with a few other texts: they are not dealt out again for each bucket."""
    rng = random.Random(12)
    base = [f"s{i}" for i in range(400)]
    data = []
    for i in range(150):
        copy = list(base)
        for x in rng.sample(range(400), 8):
            copy[x] = f"c{rng.randrange(10**6)}"
        data.append((i, " ".join(copy)))
    data += [(1000 + i, " ".join(base[10 * i : 10 * i + 200] + [f"w{rng.randrange(10**6)}" for _ in range(150)])) for i in range(20)]
    df = spark.createDataFrame(data, "doc_id long, text string").repartition(4)
    moved, deal = [], type(df).repartition

    def counted(self, *by):
        if by == ("s", "i", "j"):
            moved.append(self.count())
        return deal(self, *by)

    monkeypatch.setattr(type(df), "repartition", counted)
    got = {r["doc_id"]: r["class_id"] for r in order_minhash.membership(df).collect()}
    assert got == {i: 0 if i < 1000 else i for i, _ in data}
    assert moved and sum(moved[1:]) < 10 * len(data)


@pytest.mark.parametrize("listed", [True, False])
def test_pairs_of_several_buckets_come_out_once(listed):
    """Where the buckets of both components are known, in the least one that they share; otherwise in each."""
    count = np.ones((6, order_minhash.BINS), np.uint8)
    s, label = [3, 3, 5, 5, 5, 9], [70, 80, 70, 80, 90, 90]
    buckets = {70: [5, 3], 80: [3, 5], 90: [9, 5]} if listed else {}
    numbers = {"s": s, "i": [0] * 6, "j": [0] * 6, "part": [0] * 6, "label": label, "members": [1, 1, 1, 1, 4, 4], "least": [256] * 6, "most": [256] * 6}
    cols = [pa.array(x, pa.int64()) for x in numbers.values()]
    batch = pa.RecordBatch.from_arrays([*cols, *[order_minhash._binary(count)] * 2, pa.array([buckets.get(x) for x in label], pa.list_(pa.int64()))], [*numbers, "low", "high", "buckets"])
    out = [tuple(r.values()) for b in order_minhash._meet()([batch.slice(0, 4), batch.slice(4)]) for r in b.to_pylist()]
    want = [(70, 80, 0), (90, 70, 1), (90, 80, 1)]
    assert sorted(out) == want if listed else set(out) == set(want)


def test_boxes_hold_their_members():
    """Two components have room for a link wherever two of their members have; rows of one component may come in any order."""
    rng = np.random.default_rng(3)
    counts = rng.integers(0, 3, (60, order_minhash.BINS)).astype(np.uint8)
    counts[::2] = counts[0]
    for x in counts[::2]:
        x[rng.integers(0, order_minhash.BINS, 40)] += 1
    many, label = counts.sum(1).astype(np.int64), rng.integers(0, 12, 60)
    names = ["label", "members", "least", "most", "low", "high"]
    batch = pa.RecordBatch.from_arrays([pa.array(label), pa.array(np.ones(60, np.int64)), pa.array(many), pa.array(many), *[order_minhash._binary(counts)] * 2], names)
    (box,) = order_minhash._boxes([batch.slice(0, 25), batch.slice(25)])
    name, members, least, most = (box.column(c).to_numpy() for c in names[:4])
    low, high = (order_minhash._table(box.column(c)) for c in names[4:])
    assert dict(zip(name.tolist(), members.tolist())) == collections.Counter(label.tolist())
    place = {x: i for i, x in enumerate(name.tolist())}
    for x in range(60):
        room = order_minhash.room_between(counts[x], counts, many[x], many)
        a, b = place[label[x]], [place[y] for y in label]
        assert (order_minhash.room_of_boxes(low[a], high[a], low[b], high[b], least[a], most[a], least[b], most[b]) >= room).all()


@pytest.mark.parametrize("n", [32, 60, 100, 150, 190, 250, 400])
def test_sketches_see_the_bound(n):
    """Recall of the candidates alone, for texts with a fifth, and a tenth, of their words changed at random places."""
    rng = np.random.default_rng(n)

    def named(lists):
        names = np.concatenate([np.array([zlib.crc32(w.encode()) for w in x], np.uint64) for x in lists])
        text, code = order_minhash.names_of(order_minhash.mix(names), np.cumsum([0, *map(len, lists)]))
        return [set(code[text == i].tolist()) for i in range(len(lists))]

    for share, least in ((0.2, 0.9), (0.1, 0.99)):
        a = [[f"w{rng.integers(3000)}" for _ in range(n)] for _ in range(200)]
        b = [list(x) for x in a]
        for x in b:
            for i in rng.choice(n, int(share * n + 1e-9), replace=False):
                x[i] = f"c{rng.integers(10**9)}"
        assert sum(bool(x & y) for x, y in zip(named(a), named(b))) >= least * 200


def test_near_copies_at_the_bound(spark):
    """Against brute force: no short text misses, long ones hardly."""
    rng = random.Random(9)
    shared = [f"s{i}" for i in range(60)]
    data = []
    for g in range(60):
        n = rng.choice([5, 6, 9, 10, 11, 20, 24, 25, 29, 30, 31, 40, 90])
        body = [f"w{rng.randrange(4000)}" for _ in range(n)] + shared[: rng.choice([0, n])]
        data.append(body)
        for share in (0.1, 0.2):
            copy = list(body)
            for x in rng.sample(range(len(copy)), int(share * len(copy))):
                copy[x] = f"c{rng.randrange(10**6)}"
            data.append(copy)
    near = [[order_minhash.alike(a, b) for b in data] for a in data]
    label = list(range(len(data)))
    for _ in data:
        label = [min(label[j] for j, x in enumerate(row) if x) for row in near]
    df = spark.createDataFrame([(i, " ".join(t)) for i, t in enumerate(data)], "doc_id long, text string").repartition(4)
    got = {r["doc_id"]: r["class_id"] for r in order_minhash.membership(df).collect()}
    assert all(got[i] == x for i, x in enumerate(label) if len(data[i]) <= 24)
    assert sum(got[i] == x for i, x in enumerate(label)) >= 0.98 * len(data)


def test_unrelated_texts_of_one_id_stay(spark):
    data = [(None, "alpha beta gamma"), (None, "delta epsilon zeta"), (7, "one two three"), (7, "four five six"), (7, "four  five six"), (8, "one two three"), (8, "one two three"), (None, "one two three")]
    df = spark.createDataFrame(data, "doc_id long, text string")
    kept = rows(order_minhash.keep_one(df), "doc_id", "text")
    assert len(kept) == 4 and {" ".join(t.split()) for _, t in kept} == {"alpha beta gamma", "delta epsilon zeta", "one two three", "four five six"}
    label = {(r["doc_id"], r["label"]) for r in order_minhash.membership(df).collect()}
    assert len({x for _, x in label}) == 4


# --- 10 -----------------------------------------------------------------------------------------------------------------------
@pytest.mark.parametrize("limit", [winnowing.BROADCAST_BYTES, 0])
def test_winnowing(spark, docs, none, limit):
    items = [(1, ITEM), (2, PASSAGE), (3, "one"), (4, "gnu general"), (5, None), (6, "  "), (7, "a b c d"), (8, ITEM), (None, "license v3")]
    bench = spark.createDataFrame(items, "item_id long, text string").withColumn("w", F.lit(1))
    windows = collections.defaultdict(set)
    for i, t in items:
        w = TERM.findall((t or "").translate(ASCII))
        for k in range(len(w) - min(13, len(w)) + 1 if w else 0):
            windows[tuple(w[k : k + min(13, len(w))])].add(i)
    want = []
    for i, t in ROWS:
        w = TERM.findall((t or "").translate(ASCII))
        hit, got = set(), set()
        for size in {len(x) for x in windows}:
            for k in range(len(w) - size + 1):
                if (x := tuple(w[k : k + size])) in windows:
                    hit |= set(range(k, k + size))
                    got |= windows[x] - {None}
        want.append((i, len(w), len(hit), len(got), hashlib.sha256(",".join(sorted(map(str, got))).encode()).hexdigest(), bool(hit) and 20 * len(hit) >= len(w)))
    out = winnowing.assess(docs, bench, limit)
    assert rows(out, "doc_id", "n_words", "n_hit", "n_items", "items_sha256", "contaminated") == sorted(want, key=str)
    clean = winnowing.keep_clean(docs, bench, limit)
    assert clean.columns == docs.columns and clean.count() == sum(not x[-1] for x in want)
    assert winnowing.assess(none, bench, limit).isEmpty() and not winnowing.assess(docs, bench.limit(0), limit).where("contaminated").count()


def test_rows_of_one_id_are_not_mixed_up(spark):
    """Many texts without an id: each keeps its own verdict and words."""
    texts = [f"{' '.join(f'w{i}x{k}' for k in range(3 + i % 5))}" for i in range(400)]
    df = spark.createDataFrame([(None, t) for t in texts] + [(None, ITEM)], "doc_id long, text string")
    bench = spark.createDataFrame([(1, ITEM)], "item_id long, text string")
    out = winnowing.assess(df, bench).collect()
    assert sorted(r["n_words"] for r in out) == sorted([len(t.split()) for t in texts] + [len(TERM.findall(ITEM.translate(ASCII)))]) and sum(r["contaminated"] for r in out) == 1
    assert winnowing.keep_clean(df, bench).count() == 400


# --- pipeline -------------------------------------------------------------------------------------------------------------------
def test_pipeline(spark, tmp_path, labels, reference):
    import corpus_pipeline

    long = [words(120) for _ in range(30)]
    data = [(i, t) for i, t in enumerate(long)] + [(100, long[0]), (101, long[1] + " end"), (102, "short"), (103, ITEM + " " + words(40)), (104, words(30) + " " + PASSAGE + " " + words(50)), (105, words(45) + " " + PASSAGE + " " + words(35))]
    spark.createDataFrame([(i, t, "en", "s", len(t)) for i, t in data], "doc_id long, text string, lang string, source string, n_chars long").write.parquet(f"{tmp_path}/documents.parquet")
    spark.createDataFrame([(i, 1, 0) for i in range(30)], "doc_id long, quality int, toxic int").write.parquet(f"{tmp_path}/labels.parquet")
    spark.createDataFrame([(1, ITEM)], "item_id long, text string").write.parquet(f"{tmp_path}/benchmark.parquet")
    out = {r["doc_id"]: r for r in corpus_pipeline.run(spark, str(tmp_path)).collect()}
    assert set(out) == {*range(30), 104, 105}
    texts = dict(data)
    assert all(reference.decode(list(out[i]["ids"])) == texts[i] for i in range(30))
    passage = PASSAGE.split()
    for i in (104, 105):
        assert reference.decode(list(out[i]["ids"])).split() == [w for w in texts[i].replace(PASSAGE, " ").split()] and passage
