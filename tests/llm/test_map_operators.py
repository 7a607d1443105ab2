"""Operators without a shuffle of texts: against brute force, and on nulls, empty tables, ties and clashing names."""

import hashlib
import itertools
import random
import re
import zlib

import numpy as np
import pytest

from segcompare.llm import packing, pii, quality_rules, token_counts, tokens, toxicity

ODD = [(1, None), (2, ""), (None, "a b c"), (3, " \n\t "), (4, "x " * 40000), (4, "same text here"), (4, "same text here"), (5, "é ü  日本 \U0001f600 <|endoftext|> b")]


@pytest.fixture
def odd(spark):
    return spark.createDataFrame([(i, t, "s", 7) for i, t in ODD], "doc_id long, text string, n_words string, kept int")


def words(text):
    return re.findall(r"[^\x20\x09-\x0D]+", text or "")


def brute_repeats(w):
    best = [0] * len(w)
    for i in range(len(w)):
        for j in range(len(w)):
            k = 0
            while i != j and max(i, j) + k < len(w) and w[i + k] == w[j + k]:
                k += 1
            best[i] = max(best[i], k)
    return best


def test_repeat_lengths_match_brute_force():
    rng = random.Random(3)
    docs = [[rng.choice("abc") for _ in range(rng.randint(0, 40))] for _ in range(30)] + [list("a" * 33)]
    ids = np.array([ord(c) for d in docs for c in d])
    owner = np.repeat(np.arange(len(docs)), [len(d) for d in docs])
    assert quality_rules.repeat_lengths(ids, owner).tolist() == [x for d in docs for x in brute_repeats(d)]


def test_maximal_repeats():
    assert quality_rules.maximal_repeats([b"a", b"b", b"c", b"x", b"a", b"b", b"c"], 2) == [(0, 3), (4, 3)]


def test_quality_base_counts(spark, odd):
    got = {(r.doc_id, r.n_words): r for r in quality_rules.judge_documents(odd).collect()}
    assert len(got) == len(ODD) - 1
    for doc_id, text in ODD:
        w = words(text)
        r = got[doc_id, len(w)]
        assert r.word_chars == sum(map(len, w)) and r.n_symbols == len(re.findall(r"[#*$%&|<>]", text or ""))
        if len(w) < 1000:
            t = [tuple(w[i : i + 3]) for i in range(len(w) - 2)]
            hit = {i + k for i, x in enumerate(t) if t.count(x) > 1 for k in range(3)}
            assert r.n_repeat_words == len(hit) and r.base_failed == (len(w) < 50 or 2 * len(hit) > len(w))
    assert quality_rules.filter_documents(odd.filter("doc_id = 1")).count() == 0
    assert quality_rules.judge_documents(odd.filter("false")).count() == 0


def test_quality_verdict_matches_brute_force(spark):
    rng = random.Random(12)
    rows = []
    for k in range(40):
        w = [rng.choice("abcdefghijklmnop") + rng.choice("xyz") for _ in range(rng.randint(40, 70))]
        for _ in range(rng.randint(0, 2)):
            a, n = rng.randrange(len(w)), rng.randint(8, 24)
            at = rng.randrange(len(w))
            w[at:at] = w[a : a + n]
        rows.append((k, " ".join(w)))
    rows += [(3, rows[3][1]), (None, rows[4][1])]
    limits = quality_rules.Limits(max_longest=20)
    got = sorted((r.doc_id if r.doc_id is not None else -1, round(r.repeat_share, 9), r.longest_repeat, r.kept) for r in quality_rules.judge_documents(spark.createDataFrame(rows, "doc_id long, text string"), limits).collect())
    want = []
    for k, t in rows:
        w = t.split()
        best = brute_repeats(w)
        under = {i + j for i in range(len(w)) if best[i] >= 8 for j in range(best[i])}
        triples = {i + j for i in range(len(w) - 2) if best[i] >= 3 for j in range(3)}
        failed = len(w) < 50 or 100 * len(triples) > 50 * len(w)
        share = len(under) / len(w)
        want.append((-1 if k is None else k, round(share, 9), max(best), not failed and share <= limits.max_share and max(best) <= 20))
    assert got == sorted(want) and len({x[3] for x in want}) == 2


def test_tokenizers_agree_on_given_documents(spark):
    fast = tokens.ByteTokenizer()
    for r in spark.read.parquet("/root/testdata/sf0.001/documents.parquet").select("text").collect():
        if r.text:
            assert fast.encode(r.text) == fast.slow().encode(r.text, add_special_tokens=False).ids


def test_packing_keeps_the_rules_placement():
    rng = random.Random(5)
    packer, held, at = packing.SumOfSquaresPacker(64), {}, {}
    for k in range(400):
        n = rng.randint(1, 63)
        s, offset = packer.place(n)
        held.setdefault(s, []).append((k, 0, n, np.arange(n, dtype="<u4"), n, offset))
        at[s] = at.get(s, 0) + n
        if at[s] == 64:
            held.pop(s)
    placed = {p[0]: (s, p[5]) for s, pieces in held.items() for p in pieces}
    out = packing.finish(held, 64, packer.new)
    assert sum(p[2] for p in out) == sum(p[2] for pieces in held.values() for p in pieces)
    fill = {}
    for doc, start, length, ids, n, s, offset in sorted(out, key=lambda p: (p[5], p[6])):
        assert offset == fill.get(s, 0) and len(ids) == length
        fill[s] = offset + length
    assert all(x == 64 or x & (x - 1) == 0 for x in fill.values())
    stayed = sum(placed[doc] == (s, offset) and length == n for doc, _, length, _, n, s, offset in out)
    assert stayed > 0.6 * len(placed)


def test_quality_method_rejects_what_the_base_rule_keeps():
    new = lambda n, c: [f"{c}{k}" for k in range(n)]
    shared, long_one = new(40, "s"), new(120, "l")
    texts = [new(120, "a") + shared + shared, new(760, "b") + long_one + ["between"] + long_one, new(160, "c") + new(20, "d") * 2]
    got = quality_rules._judge([" ".join(w).encode() for w in texts], quality_rules.Limits())
    assert list(got["base_failed"]) == [False] * 3
    assert list(got["kept"]) == [False, False, True]
    assert list(got["longest_repeat"]) == [40, 120, 20] and got["repeat_share"][0] == 0.4


def test_quality_duplicate_lines(spark):
    df = spark.createDataFrame([(1, "a b\n\n \na b\nc\na b\nc ")], "doc_id long, text string")
    assert quality_rules.judge_documents(df).first().n_dup_lines == 2


def test_tokenizers_agree():
    tok = tokens.ByteTokenizer()
    rng = random.Random(5)
    pool = [chr(c) for c in range(256)] + list(" \n\t'sdrevl0123 ")
    for _ in range(400):
        text = "".join(rng.choice(pool) for _ in range(rng.randint(0, 60))) + rng.choice(["", "<|endoftext|>", " <|endoftext|> x"])
        assert tok.encode(text) == tok.slow().encode(text, add_special_tokens=False).ids


def test_packing_is_whole_and_tight(spark, odd):
    tok = tokens.ByteTokenizer()
    docs = [(k, " ".join(f"w{k}{i}" for i in range(k * 7 % 90))) for k in range(200)]
    df = spark.createDataFrame(docs, "doc_id long, text string").coalesce(2)
    rows = packing.pack_documents(df, room=256).collect()
    pieces, sequences = {}, {}
    for r in rows:
        pieces.setdefault(r.doc_id, []).append(r)
        sequences.setdefault(r.sequence_id, []).append(r)
    for k, text in docs:
        ids = np.array([*tok.encode(text), 0], "<u4")
        at = 0
        for r in sorted(pieces[k], key=lambda r: r.start):
            assert r.start == at and r.doc_tokens == len(ids) and r.ids_crc32 == zlib.crc32(ids[at : at + r.length].tobytes())
            at += r.length
        assert at == len(ids)
    padding = 0
    for rs in sequences.values():
        at = 0
        for r in sorted(rs, key=lambda r: r.offset):
            assert r.offset == at
            at += r.length
        assert at <= 256
        padding += 0 if at & (at - 1) == 0 else 256 - at
    assert padding == 0
    assert {r.doc_id for r in packing.pack_documents(odd).collect()} == {i for i, _ in ODD}
    assert packing.pack_documents(odd.filter("false")).count() == 0


def test_sum_of_squares_choice_is_the_best():
    rng = random.Random(1)
    packer = packing.SumOfSquaresPacker(20)
    for _ in range(500):
        size, counts = rng.randint(1, 19), packer.levels.copy()

        def cost(h, size=size, counts=counts):
            c = counts.copy()
            c[h] -= h > 0
            if h + size < 20:
                c[h + size] += 1
            return int((c[1:20] ** 2).sum())

        best = min(cost(h) for h in range(21 - size) if h == 0 or counts[h])
        _, level = packer.place(size)
        assert cost(level) == best


def test_token_counts(spark, odd):
    tok = tokens.ByteTokenizer()
    got = sorted(((r.doc_id or -1), r.n_tokens) for r in token_counts.document_token_counts(odd).collect())
    assert got == sorted(((i or -1), len(tok.encode(t or "", ordinary=True))) for i, t in ODD)
    assert token_counts.document_token_counts(odd.filter("false")).count() == 0


@pytest.mark.parametrize("block", [1, 2, 3, 7, 100])
def test_scan_stitches_blocks(spark, tmp_path, block):
    files = {"a.bin": [9, 1, 2, 9, 9, 3, 4, 5, 6, 7, 8], "b.bin": [1, 2, 3], "c.bin": [], "d.bin": [9]}
    rows = []
    for name, ids in files.items():
        np.array(ids, "<u2").tofile(tmp_path / name)
        rows.append((f"file://{tmp_path}/{name}", 2 * len(ids)))
    df = spark.createDataFrame(rows, "file string, bytes long")
    got = sorted((r.file[-5:], r.ordinal, r.start, r.n_tokens, r.closed) for r in token_counts.count_tokens(spark, df, 9, 2, block).collect())
    assert got == [("a.bin", 0, 0, 0, True), ("a.bin", 1, 1, 2, True), ("a.bin", 2, 4, 0, True), ("a.bin", 3, 5, 6, False), ("b.bin", 0, 0, 3, False), ("d.bin", 0, 0, 0, True)]


BASE = {
    "email": r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+",
    "ip": r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)",
    "card": r"[0-9]([\x20-]?[0-9])+",
    "phone": r"\+[0-9][\x20().0-9-]+[0-9]",
}


def brute_pii(text):
    out = []
    for kind, p in BASE.items():
        for m in re.finditer(p, text):
            d = re.sub("[^0-9]", "", m[0])
            if kind == "ip" and any(int(x) > 255 for x in m[0].split(".")):
                continue
            if kind == "card" and not (16 <= len(d) <= 19 and pii.passes_luhn(d)):
                continue
            if kind == "phone" and not 8 <= len(d) <= 15:
                continue
            out.append((kind, m.start(), m.end()))
    return out


def test_plain_identifiers_match_the_patterns():
    rng = random.Random(2)
    for _ in range(4000):
        text = "".join(rng.choice("ab1.@+-_ (2)é\n49") for _ in range(rng.randint(0, 40)))
        assert pii.detect(text) == brute_pii(text), text
    assert pii.detect("4337166598464399 and 4337-1665-9846-4399") == brute_pii("4337166598464399 and 4337-1665-9846-4399")


DISGUISED = [
    ("write jane.roe (at) mail (dot) example (dot) org now", "email", "jane.roe (at) mail (dot) example (dot) org"),
    ("write jane dot roe at mail dot example dot org now", "email", "jane dot roe at mail dot example dot org"),
    ("write jane[at]example.org now", "email", "jane[at]example.org"),
    ("jane@example dot org", "email", "jane@example dot org"),
    ("ｊａｎｅ＠example．org", "email", "ｊａｎｅ＠example．org"),
    ("jаne@exаmple.org", "email", "jаne@exаmple.org"),
    ("call plus one nine eight eight five five five two four eight five today", "phone", "plus one nine eight eight five five five two four eight five"),
    ("host 42[.]144[.]35[.]254 up", "ip", "42[.]144[.]35[.]254"),
    ("host 42 dot 144 dot 35 dot 254 up", "ip", "42 dot 144 dot 35 dot 254"),
    ("card ４３３７ 1665 9846 4399 ok", "card", "４３３７ 1665 9846 4399"),
    ("card four three three seven one six six five nine eight four six four three nine nine ok", "card", "four three three seven one six six five nine eight four six four three nine nine"),
]


@pytest.mark.parametrize(("text", "kind", "part"), DISGUISED)
def test_disguised_identifiers_map_back(text, kind, part):
    base, added = pii.find_identifiers(text)
    spans = [(k, text[a:b]) for k, a, b in added]
    if "jаne" in text:
        assert any(k == kind and text[a:b] == part for k, a, b in added) or any(k == kind for k, *_ in base)
    else:
        assert (kind, part) in spans


def test_clean_texts_get_nothing():
    for text in ("meet me at example.com. we look at one dot on the map", "look at the dot on the page", "un deux sont à la six", "a @ b and c", "one two buckle my shoe"):
        assert pii.find_identifiers(text) == ([], [])


def test_long_disguised_addresses():
    name, host = "n" * 200, " dot ".join(["label" * 30] * 20 + ["org"])
    text = f"write {'x.' * 12}{name} (at) {host} now, " + " " * 50000 + "and a.b.c" * 2000
    base, added = pii.find_identifiers(text)
    assert [(k, text[a:b]) for k, a, b in added] == [("email", f"{'x.' * 12}{name} (at) {host}")]


def test_pii_query_values_on_odd_rows(spark):
    texts = [None, "", "a.b@c.de 1.2.3.4 and 4337-1665-9846-4399 +49 (30) 1234567", *(t for t, *_ in DISGUISED), "é😀 a@b.cd", "a@b.cd " * 3000]
    rows = [(k, t, "x", "kept") for k, t in enumerate([*texts, texts[2], texts[2]])] + [(None, texts[2], "x", "kept"), (2, texts[2], "x", "kept")]
    df = spark.createDataFrame(rows, "doc_id long, text string, spans string, n_email string").repartition(3)
    want = []
    for k, t, *_ in rows:
        base = brute_pii(t or "")
        base.sort(key=lambda x: (pii.KINDS.index(x[0]), x[1]))
        said = ",".join(f"{kind}:{a}:{b}" for kind, a, b in base)
        added = pii.find_identifiers(t)[1]
        every = sorted([*base, *added], key=lambda x: (pii.KINDS.index(x[0]), x[1]))
        counts = [sum(x[0] == kind for x in base) for kind in ("email", "ip", "card", "phone")]
        want.append((k, *counts, hashlib.sha256(said.encode()).hexdigest(), ",".join(f"{kind}:{a}:{b}" for kind, a, b in every)))
    got = [tuple(r)[:7] for r in pii.personal_data(df).collect()]
    assert sorted(got, key=str) == sorted(want, key=str)
    clash = spark.createDataFrame([(1, "mail a@b.cd", "many")], "doc_id long, text string, n_chars string")
    assert [tuple(r) for r in pii.mask_documents(clash).collect()] == [(1, "mail <EMAIL>", "many")]


def test_pii_rows(spark, odd):
    assert pii.personal_data(odd).count() == len(ODD)
    assert pii.mask_documents(odd).columns == odd.columns
    assert pii.mask("mail a@b.c now", [("email", 5, 10)]) == "mail <EMAIL> now"


def test_toxicity_long_disguised_runs():
    plain = "the long walk by the river and the old mill on the hill was soft and green you are an idiot said the man " * 40
    s = toxicity._symbols("  " + plain + "  ")
    n = toxicity._SIZE
    model = toxicity.log_model(np.bincount(s[:-2] * n * n + s[1:-1] * n + s[2:], minlength=n**3).reshape(n, n, n))
    letters = "thelongwalkbytheriverandtheoldmillonthehillwassoftandgreenyouareanidiot"
    for sign in ".-*_~ ":
        run = sign.join(letters)
        assert toxicity.Restorer(model).suspects(f"so {run} now") >= {run}
        read = toxicity.viterbi(run, model)
        assert read.replace(" ", "") == letters and "idiot" in read.split()
        assert b"idiot" in toxicity.Restorer(model).words(f"so {run} now")
    token = "x" * 5 + "-" + "the" * 30 + "-1d10t"  # one token of more than 64 characters
    assert toxicity.Restorer(model).suspects(f"so {token} !") == {token}
    assert len(toxicity.viterbi(".".join(letters * 60), model).replace(" ", "")) == 60 * len(letters)


def small_model():
    plain = "the long walk by the river and the old mill on the hill was soft and green that you are an idiot and a moron said the man to him " * 40
    s = toxicity._symbols("  " + plain + "  ")
    n = toxicity._SIZE
    return toxicity.log_model(np.bincount(s[:-2] * n * n + s[1:-1] * n + s[2:], minlength=n**3).reshape(n, n, n))


def test_viterbi_finds_the_cheapest_of_all_paths():
    model, rng = small_model(), random.Random(8)
    words_ = ["1d10t", "m0r0n", "to!!", "!d!ot", "h1ll", "oolldd", "t.h.e", "m-o-r-o-n", "w*lk", "ri|er"]
    words_ += ["".join(rng.choice("thei10!4@lo") for _ in range(rng.randint(1, 6))) for _ in range(150)]
    for word in words_:
        paths = list(itertools.product(*toxicity.lattice(word)))
        costs = [toxicity.path_cost(p, model) for p in paths]
        least = {"".join(w for w, _ in p).strip() for p, c in zip(paths, costs, strict=True) if c <= min(costs) + 1e-4}
        assert toxicity.viterbi(word, model) in least


def test_channel_leaves_clean_words_and_helps_disguised_ones(spark):
    model = small_model()
    restorer = toxicity.Restorer(model)
    for text in ("to!! that!! hill! (the) mill* and $ the 10 men", "said the man!!! to him!!", "the hill, the mill."):
        assert restorer.words(text) == restorer.words(text, channel=False), text
    assert b"idiot" in restorer.words("you \u0456di\u043et said")  # letters of another script
    weights = ({b"=idiot": 6.0, b"=moron": 6.0}, -3.0)
    disguised = [(k, f"the man by the river is {w} said him") for k, w in enumerate(["an 1d10t", "a m0r0n", "a m.o.r.o.n", "an i d i o t", "an !diot", "a morrrrron"])]
    clean = [(100 + k, t) for k, t in enumerate(["the man said to!! him", "the old mill!! on the hill", None, ""])]
    df = spark.createDataFrame([*disguised, *clean, (0, disguised[0][1]), (None, disguised[1][1])], "doc_id long, text string")
    with_, without = ([(r.doc_id, r.predicted) for r in toxicity.score_documents(df, (model, *weights), channel=c).collect()] for c in (True, False))
    assert sum(y for _, y in with_) == len(disguised) + 2 and sum(y for _, y in without) == 0
    assert all(y == 0 for k, y in with_ if k is not None and k >= 100)


def test_toxicity_query_matches_a_plain_scorer(spark):
    rng = random.Random(6)
    vocabulary = ["river", "mill", "hill", "bread", "salt", "honey", "idiot", "1d10t", "to!!", "m o r o n", "moron"]
    rows = [(k, " ".join(rng.choice(vocabulary) for _ in range(rng.randint(0, 12)))) for k in range(120)] + [(7, "again idiot"), (None, "moron"), (130, None), (131, "idiot " * 20000)]
    df = spark.createDataFrame([(*r, 1, "x") for r in rows], "doc_id long, text string, toxic int, score string").repartition(3)
    labels = spark.createDataFrame([(k, int("idiot" in (t or "") or "moron" in (t or ""))) for k, t in rows if k is not None and k < 120], "doc_id long, toxic int")
    model, weights, bias = toxicity.train(df, labels)
    got = sorted(((r.doc_id is None, r.doc_id or 0, r.held_out, round(r.score, 9), r.predicted) for r in toxicity.score_documents(df, (model, weights, bias)).collect()))
    want = []
    for k, t in rows:
        restorer = toxicity.Restorer(model)
        seen = {f for w in restorer.words(t) for f in toxicity.features(w)}
        z = bias + sum(weights.get(f, 0.0) for f in sorted(seen))
        score = 1 / (1 + np.exp(-z))
        want.append((k is None, k or 0, k is not None and zlib.crc32(str(k).encode()) % 5 == 0, round(float(score), 9), int(score >= 0.5)))
    assert got == sorted(want)


def test_toxicity_restores_and_scores(spark):
    rng = random.Random(4)
    plain = ["the rain in the hills was soft and green", "a long walk by the river and the old mill", "the market sells bread and salt and honey"]
    rows, labels = [], []
    for k in range(600):
        bad = k % 4 == 0
        w = [*rng.choice(plain).split(), *rng.choice(plain).split()]
        if bad:
            w.insert(rng.randrange(len(w)), rng.choice(["idiot", "moron", "loser"]))
        rows.append((k, " ".join(w)))
        labels.append((k, int(bad)))
    docs = spark.createDataFrame([*rows, (9001, "the 1d10t by the river"), (9002, "the m o r o n by the river"), (9003, "the looooser by the river"), (9004, "the loaf by the river"), (9005, None), (9006, "")], "doc_id long, text string")
    fitted = toxicity.train(docs, spark.createDataFrame([*labels, (None, 1), (3, None)], "doc_id long, toxic int"))
    got = {r.doc_id: r for r in toxicity.score_documents(docs, fitted).collect()}
    assert all(got[k].predicted == y for k, y in labels)
    assert [got[k].predicted for k in (9001, 9002, 9003, 9004, 9005, 9006)] == [1, 1, 1, 0, 0, 0]
    assert toxicity.score_documents(docs.filter("false"), fitted).count() == 0
    empty = toxicity.train(docs.filter("false"), spark.createDataFrame([], "doc_id long, toxic int"))
    assert 0 < toxicity.score_documents(docs, empty).first().score < 1
