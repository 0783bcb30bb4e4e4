import itertools
import random
import re
import zlib

import numpy as np
import public_tokenizers
import pytest
from tokenizers import Tokenizer

from tests.llm.test_dedup import table
from treegrammar.llm import bpe, decontaminate, language, license_scan, toxicity
from treegrammar.llm.queries import tokenizer_text
from treegrammar.llm.recurrent import BiGru, BiLstm

# BPE


@pytest.fixture(scope="module")
def coder():
    return bpe.Bpe(tokenizer_text())


AWKWARD = ["", " ", "a<|endoftext|>b<|endoftext|>", "<|endoftext|", "aaaaaaaaaaaaaaaaaaaaaaaaa", "\x1c\x1d\x85\u2028 x", "don't I'LL we've'", "   x  \n\n y\t", "日本語 テキスト🎉🎉", "a\u0300e\u0301", "x" * 3000, "123 4567 ½ Ⅷ", "\x00\x01", " \u00a0 \u3000z"]


def test_encoding_equals_the_library(coder):
    library = Tokenizer.from_file(public_tokenizers.path("byte_bpe_50k.json"))
    rng = random.Random(3)
    texts = AWKWARD + ["".join(rng.choice("abcdeg thionr ,.'é\n1\U0001f600") for _ in range(rng.randint(0, 120))) for _ in range(400)]
    for t, (ids, n, raw), e in zip(texts, coder.encode_texts(texts), library.encode_batch(texts, add_special_tokens=False), strict=True):
        assert ids == ",".join(map(str, e.ids)) and n == len(e.ids), t
        assert raw.decode("utf-8", "replace") == library.decode(e.ids, skip_special_tokens=False) == t


def test_every_token_encodes_to_itself(coder):
    rng = random.Random(5)
    some = rng.sample(sorted(coder.ids), 3000)
    assert all(ids == [coder.ids[w]] for w, ids in coder.encode_words(some))


def test_encode_and_decode_tables(spark):
    rows = [(k, t) for k, t in enumerate([*AWKWARD, None])]
    text = tokenizer_text()
    ids = bpe.encode(table(spark, rows), text)
    back = {r["doc_id"]: r["text"] for r in bpe.decode(ids, text).collect()}
    assert back == {k: t or "" for k, t in rows}
    assert {r["doc_id"]: r["n_tokens"] for r in bpe.digests(table(spark, rows), text).collect()} == {r["doc_id"]: len(r["ids"]) for r in ids.collect()}
    assert bpe.digests(table(spark, []), text).count() == 0


def test_bpe_automaton_gives_every_token_that_ends_at_a_byte(monkeypatch):
    """Also when the steps that are kept start anew all the time; ids are those of the library."""
    library = Tokenizer.from_file(public_tokenizers.path("byte_bpe_50k.json"))
    for steps in (bpe.CACHE_STEPS, 5):
        monkeypatch.setattr(bpe, "CACHE_STEPS", steps)
        b, rng, state, read = bpe.Bpe(tokenizer_text()), random.Random(4), 0, b""
        for _ in range(400):
            read += bytes([rng.choice(b"ionthe zz\xc3\xa9")])
            state = b.step(state, read[-1])
            assert [size for _, size in b.ends[state]] == [k for k in range(min(len(read), 200), 0, -1) if read[-k:] in b.ids]
            assert all(b.ids[read[-size:]] == t for t, size in b.ends[state])
        assert len(b.goto) <= steps + 1
        words = ["".join(rng.choice("inothe\u00e9") for _ in range(rng.randint(1, 14))) for _ in range(300)]
        for w, (ids, n, back) in zip(words, b.encode_texts(words), strict=True):
            assert ids == ",".join(map(str, library.encode(w, add_special_tokens=False).ids)) and n == ids.count(",") + 1 and back.decode() == w


# Decontamination

RNG = random.Random(7)
WORDS = ["".join(RNG.choice("abcdefghijklmnop") for _ in range(RNG.randint(2, 9))) for _ in range(4000)]


def sentence(n, rng=RNG):
    return " ".join(rng.choice(WORDS) for _ in range(n))


def slow_overlaps(doc, items, min_words=decontaminate.MIN_WORDS, min_share=decontaminate.MIN_SHARE):
    """Items with a stretch of equal offsets that has enough equal words: every offset and every pair of ends is tried."""
    d, out = decontaminate.words(doc), set()
    for item_id, text in items:
        w = decontaminate.words(text)
        if len(w) < decontaminate.TOLERANT:
            if w and any(d[k : k + len(w)] == w for k in range(len(d))):
                out.add(item_id)
            continue
        need = min(min_words, int(np.ceil(0.9 * len(w))))
        for shift in range(-len(w), len(d)):
            eq = [d[shift + k] == w[k] for k in range(len(w)) if 0 <= shift + k < len(d)]
            best = any(sum(eq[a:b]) >= need and sum(eq[a:b]) >= min_share * (b - a) for a in range(len(eq)) for b in range(a + need, len(eq) + 1) if eq[a] and eq[b - 1])
            if best:
                out.add(item_id)
                break
    return out


def test_overlaps_against_brute_force():
    items = [(k, sentence(n)) for k, n in enumerate((3, 7, 8, 12, 15, 30, 59))]
    block = decontaminate.TestBlock(items)
    rng = random.Random(9)
    for trial in range(120):
        item = items[trial % len(items)][1].split(" ")
        if trial % 3 == 1 and len(item) > 14:  # substitutions, at least four words apart
            for k in range(trial % 4, len(item), 6):
                item[k] = "changed"
        if trial % 3 == 2:
            item = item[: rng.randint(1, len(item))]
        doc = sentence(rng.randint(0, 20), rng) + " " + " ".join(item).upper() + ", " + sentence(rng.randint(0, 20), rng)
        assert {x[0] for x in block.overlaps(doc)} == slow_overlaps(doc, items), doc


def test_masks_leave_no_pattern_of_substitutions():
    """All ways to put as many substitutions as the thresholds allow into 8 to 29 words; longer stretches hold one of these."""
    for n in range(decontaminate.TOLERANT, 30):
        need = int(np.ceil(0.9 * n)) if n < 14 else max(decontaminate.MIN_WORDS, int(np.ceil(decontaminate.MIN_SHARE * n)))
        gone = np.array([sum(1 << k for k in c) for c in itertools.combinations(range(n), n - min(need, n))], np.int64)
        hit = np.zeros(len(gone), bool)
        for mask in decontaminate.MASKS:
            for at in range(n - mask[-1]):
                hit |= gone & sum(1 << at + k for k in mask) == 0
        assert hit.all(), (n, int((~hit).sum()))


def test_substitutions_at_the_threshold():
    """Passages with the reviewed pattern and random ones, through the operator."""
    rng = random.Random(4)
    for n, changed in [(15, (2, 4, 9)), (10, (4,))] + [(n, rng.sample(range(n), n // 5)) for n in range(15, 45) for _ in range(4)]:
        words = sentence(n).split(" ")
        block = decontaminate.TestBlock([(1, " ".join(words))])
        for k in changed:
            words[k] = "changed"
        assert [x[0] for x in block.overlaps("before it " + " ".join(words) + " behind it")] == [1], (n, changed)


def test_short_items_must_stand_whole():
    items = [(k, sentence(k)) for k in range(8)] + [(20, "..."), (21, "cake")]
    block = decontaminate.TestBlock(items)
    rng = random.Random(6)
    for k, text in items:
        own = text.split(" ") if text else []
        changed = ["changed", *own[1:]]
        for doc in (sentence(9, rng) + " " + text + " " + sentence(5, rng), text, " ".join(own[:-1]), " ".join(changed), "cake " * 40):
            assert {x[0] for x in block.overlaps(doc)} == slow_overlaps(doc, items), (k, doc)
    assert block.overlaps("a cake, a cake") == [(21, 1, 1, 1, 0)] and block.overlaps(None) == []


def test_rows_are_cleaned_by_their_own_text(spark):
    """Null and repeated ids: a row goes if its own text holds a passage."""
    item = sentence(20)
    rows = [(None, item), (None, "clean"), (1, "also clean"), (1, "x " + item), (1, "also clean")]
    tests = spark.createDataFrame([(1, item)], "item_id long, text string")
    got = sorted(((r["doc_id"], r["text"]) for r in decontaminate.clean(spark, table(spark, rows), tests).collect()), key=str)
    assert got == sorted([(None, "clean"), (1, "also clean"), (1, "also clean")], key=str)
    found = decontaminate.overlaps(spark, table(spark, [(1, "y z " + item), (1, item + " q"), (None, item)]), tests).collect()
    assert {(r["doc_id"], r["equal_words"], r["doc_word"]) for r in found} == {(1, 20, 0), (None, 20, 0)}


def test_every_planted_passage_is_found_and_no_clean_document(spark):
    items = [(k, sentence(RNG.randint(15, 59))) for k in range(30)]
    rows, truth = [], set()
    for k in range(200):
        body = [sentence(40), sentence(30)]
        if k % 4 == 0:
            item = items[k % 30]
            body.insert(1, item[1])
            truth.add((k, item[0]))
        rows.append((k, "\n".join(body)))
    tests = spark.createDataFrame([(i, t, "clash") for i, t in items] + [(99, None, "x"), (98, "", "x")], "item_id long, text string, doc_id string")
    rows += [(500, None), (501, ""), (502, "word")]
    got = {(r["doc_id"], r["item_id"]) for r in decontaminate.overlaps(spark, table(spark, rows), tests).collect()}
    assert got == truth
    kept = {r["doc_id"] for r in decontaminate.clean(spark, table(spark, rows), tests).collect()}
    assert kept == {i for i, _ in rows} - {d for d, _ in truth}
    assert decontaminate.overlaps(spark, table(spark, rows), tests.limit(0)).count() == 0
    assert decontaminate.overlaps(spark, table(spark, []), tests).count() == 0


def test_blocks_of_tests_give_the_same(spark, monkeypatch):
    items = [(k, sentence(20)) for k in range(12)]
    rows = [(k, sentence(10) + " " + items[k % 12][1]) for k in range(24)]
    tests = spark.createDataFrame(items, "item_id long, text string")
    one = {tuple(r) for r in decontaminate.overlaps(spark, table(spark, rows), tests).collect()}
    monkeypatch.setattr(decontaminate, "BLOCK_WORDS", 60)
    assert {tuple(r) for r in decontaminate.overlaps(spark, table(spark, rows), tests).collect()} == one and len(one) == 24


# License scan


def slow_scan(text):
    w = re.findall(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+", "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in text or ""))
    found = [(k, label) for label, phrase in license_scan.BASE for k in range(len(w)) if w[k : k + len(phrase.split())] == phrase.split()]
    return len(w), len(found), min((k for k, _ in found), default=None), max((k for k, _ in found), default=None), ",".join(sorted({x for _, x in found}))


LICENSES = [
    "", None, "...", "Released under the MIT License.", "under the mit license under the MIT-license", "Licensed under CC BY-NC 4.0. cc by nc", "the Apache License, Version 2.0 and CC BY NC", "under the mit licenses",
    "Kunder the mit license", "x" * 5000, "under the \u212a mit license", "cc\u00a0by nc cc by nc", "This work is licensed under the GNU General Public License, version 3.", "ccc by nc", "İ under the mit license", "under the mit", "1apache license version 2",
]


def test_license_scan(spark):
    rng = random.Random(2)
    pool = "under the mit license apache version 2 cc by nc foo é".split(" ")
    texts = LICENSES + [rng.choice([" ", ", "]).join(rng.choice(pool) for _ in range(rng.randint(0, 60))) for _ in range(150)]
    rows = list(enumerate(texts))
    got = {r["doc_id"]: r for r in license_scan.scan(table(spark, rows)).collect()}
    assert len(got) == len(rows)
    for i, t in rows:
        r = got[i]
        assert (r["n_words"], r["n_base"], r["first_word"], r["last_word"], r["base_labels"]) == slow_scan(t), t
        assert set(filter(None, r["base_labels"].split(","))) <= set(filter(None, r["labels"].split(","))) and 0 <= r["score"] <= 1
    assert "gpl-3" in got[12]["labels"]


def test_license_template_with_edits(spark):
    words = license_scan.MORE[0][1].split(" ")
    rows = [(1, " ".join(words)), (2, " ".join(words[:12] + ["indeed"] + words[12:])), (3, " ".join(words[:8])), (4, "x " * 50)]
    got = {r["doc_id"]: r["labels"] for r in license_scan.scan(table(spark, rows)).collect()}
    assert got == {1: "mit", 2: "mit", 3: "", 4: ""}
    assert license_scan.scan(table(spark, [])).count() == 0
    assert license_scan.scan(table(spark, [(1, "a b c"), (1, "a b c"), (None, "d")])).count() == 3


# Networks, language, toxicity


@pytest.mark.parametrize("kind", ["gru", "lstm"])
def test_gradients(kind):
    rng = np.random.default_rng(0)
    if kind == "gru":
        net, ids, y = BiGru(5, 4, 3), rng.integers(0, 5, (6, 3)), rng.integers(0, 3, (6, 3))
        run = lambda: net.gradients(ids, y, np.ones((6, 3), np.float32))
    else:
        net, x, mask = BiLstm(5, 4), rng.standard_normal((6, 3, 5)).astype(np.float32), np.ones((6, 3), np.float32)
        mask[4:, 1] = 0
        y = rng.integers(0, 2, (6, 3)).astype(np.float32)
        run = lambda: net.gradients(x, mask, y)
    _, g = run()
    for k in net.p:
        for _ in range(4):
            at = tuple(int(rng.integers(s)) for s in net.p[k].shape)
            v = net.p[k][at]
            net.p[k][at] = v + 1e-2
            up = run()[0]
            net.p[k][at] = v - 1e-2
            down = run()[0]
            net.p[k][at] = v
            assert abs((up - down) / 2e-2 - g[k][at]) < 2e-3 + 0.05 * abs(g[k][at]), k


def test_language_held_out_accuracy(spark):
    df = spark.read.parquet("/root/testdata/sf0.01/documents.parquet")
    from treegrammar.llm.queries import op7_language

    got = op7_language(spark, "/root/testdata/sf0.01").join(df.select("doc_id", "lang"), "doc_id").collect()
    held = [r for r in got if r["held_out"]]
    assert len(got) == 1000 and all(r["held_out"] == (zlib.crc32(str(r["doc_id"]).encode()) % 5 == 0) for r in got)
    assert np.mean([r["lang_pred"] == r["lang"] for r in held]) > 0.97


def test_language_edges(spark):
    model = language.LanguageModel(["aa", "bb"])
    model.train(["xyz " * 30] * 4 + ["qrs " * 30] * 4, ["aa"] * 4 + ["bb"] * 4, steps=60)
    rows = [(1, None), (2, ""), (3, "12 -- \n \u00b2\u00bd"), (4, "xyz xyz"), (5, "qrs " * 5000), (6, "é"), (6, "é")]
    got = {r["doc_id"]: (r["lang_pred"], r["score"]) for r in language.predict(spark, table(spark, rows), model).collect()}
    assert got[1] == got[2] == got[3] == ("und", 0.0) and got[4][0] == "aa" and got[5][0] == "bb" and got[6][0] in ("aa", "bb")
    assert language.predict(spark, table(spark, []), model).count() == 0
    assert {r["lang_pred"] for r in language.predict(spark, table(spark, rows), language.LanguageModel([])).collect()} == {"und"}
    assert language.fit(spark, table(spark, [])).languages == []


def examples(n=300, seed=1):
    rng = random.Random(seed)
    bad, common = ["idiot", "scum", "trash", "moron"], WORDS[:200]
    out = []
    for i in range(n):
        y = int(i % 4 == 0)
        w = [rng.choice(common) for _ in range(rng.randint(5, 60))] + [rng.choice(bad) for _ in range(3 * y)]
        rng.shuffle(w)
        out.append((i, " ".join(w), y))
    return out


def test_block_max_search_equals_a_full_scan():
    model = toxicity.Neighbours(examples())
    for _, text, _ in examples(80, 2):
        terms, w = model.vector(text)
        if not len(terms):
            continue
        rows, sims = model.nearest(terms, w)
        full = np.zeros(len(model.ids))
        for t, x in zip(terms.tolist(), w.tolist(), strict=True):
            pieces = slice(model.of_term[t], model.of_term[t + 1])
            for at, size in zip(model.piece_start[pieces].tolist(), model.piece_size[pieces].tolist(), strict=True):
                full[model.row[at : at + size]] += x * model.w[at : at + size]
        order = np.lexsort((model.ids, -np.round(full, 6)))
        order = [k for k in order.tolist() if full[k] > 0][: model.k]
        assert rows.tolist() == order and np.allclose(sims, full[order], atol=1e-5)


def test_toxicity_edges(spark):
    model = toxicity.Neighbours(examples())
    rows = [(1, None), (2, ""), (3, "you idiot scum trash"), (4, " ".join(WORDS[:30])), (5, "idiot " * 30_000), (5, "x")]
    got = toxicity.scores(spark, table(spark, rows), model).collect()
    by = {r["doc_id"]: r for r in got if r["doc_id"] != 5}
    assert len(got) == 6 and by[1]["predicted"] == by[2]["predicted"] == by[4]["predicted"] == 0 and by[3]["predicted"] == 1 and by[3]["evidence"]
    assert {r["doc_id"] for r in toxicity.clean(spark, table(spark, rows), model).collect()} == {1, 2, 4, 5}
    empty = toxicity.Neighbours([])
    assert empty.score("idiot") == (0.0, [])
    labels = spark.createDataFrame([], "doc_id long, toxic int")
    assert toxicity.fit(spark, table(spark, []), labels).score("x")[0] == 0.0
    only = toxicity.Neighbours([(1, "a b", 0), (2, "c d", 0)])
    assert only.score("a")[0] < 0.5


def test_every_word_counts():
    """No word of an example is left out of its vector, and equal word sequences count once."""
    rows = examples()
    model = toxicity.Neighbours(rows + [(10_000 + i, t, y) for i, t, y in rows])
    assert set(model.vocab) == {w for _, t, _ in rows for w in t.split(" ")} and len(model.ids) == len({t for _, t, _ in rows})
    assert (model.term_weight > 0).all()


def test_document_frequencies(spark):
    rows = [(1, "Aa bb aa"), (2, "bb cc"), (2, "bb cc"), (3, None), (4, "")]
    assert toxicity.document_frequencies(spark, table(spark, rows), {"aa", "bb", "zz"}) == ({"aa": 1, "bb": 3}, 5)
    assert toxicity.document_frequencies(spark, table(spark, []), {"aa"}) == ({}, 0)


def test_toxicity_held_out(spark):
    """Labelled rows that the model has not seen, on the given table."""
    from treegrammar.llm.queries import op8_toxicity

    sf = "/root/testdata/sf0.1"
    got = op8_toxicity(spark, sf).join(spark.read.parquet(f"{sf}/labels.parquet").select("doc_id", "toxic"), "doc_id").where("held_out").select("predicted", "toxic").collect()
    assert np.mean([r["predicted"] == r["toxic"] for r in got]) > 0.975
