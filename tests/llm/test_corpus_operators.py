"""Operators over pairs, windows and the corpus: against brute force, and on nulls, empty tables, ties and clashing names."""

import hashlib
import itertools
import math
import random
import re
import zlib
from collections import Counter

import numpy as np
import pytest

import corpus_pipeline
from segcompare.llm import chat_windows, decontamination, ngram_join, packing, pii, ppm, quality_rules, substring_dedup

SCHEMA = "doc_id long, text string, n string, key int"


def corpus(seed=0, n=120):
    """Words from a small vocabulary, with copies, near copies and shared passages."""
    rng = random.Random(seed)
    vocabulary = [f"w{k}" for k in range(400)]
    texts = []
    passage = [rng.choice(vocabulary) for _ in range(60)]
    for _ in range(n):
        kind = rng.random()
        if texts and kind < 0.15:
            w = rng.choice(texts).split()
        elif texts and kind < 0.45:
            w = rng.choice(texts).split()
            for _ in range(rng.randint(1, 3)):
                if w:
                    w[rng.randrange(len(w))] = rng.choice(vocabulary)
        else:
            w = [rng.choice(vocabulary) for _ in range(rng.choice([0, 1, 2, 5, 9, 11, 30, 80, 200]))]
        if kind > 0.9:
            at = rng.randint(0, len(w))
            w = w[:at] + passage[rng.randint(0, 10) :] + w[at:]
        texts.append(" ".join(w))
    rows = [(k, t, "x", 1) for k, t in enumerate(texts)]
    return [*rows, (900, None, "x", 1), (901, "", "x", 1), (902, " \n ", None, None), (903, "Ab ab AB", "x", 1), (904, "ab AB ab", "x", 1), (905, "x " * 3000, "x", 1)]


@pytest.fixture(scope="module")
def rows():
    return corpus()


@pytest.fixture(scope="module")
def docs(spark, rows):
    return spark.createDataFrame(rows, SCHEMA).repartition(4)


def gram_set(text, n):
    w = [x.translate({c: c + 32 for c in range(65, 91)}) for x in re.findall(r"[^\x20\x09-\x0D]+", text or "")]
    return {tuple(w[i : i + n]) for i in range(len(w) - n + 1)} or ({tuple(w)} if w else set())


def brute_components(rows, n, percent):
    sets = [gram_set(r[1], n) for r in rows]
    root = list(range(len(rows)))

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    links = Counter()
    for a, b in itertools.combinations(range(len(rows)), 2):
        i = len(sets[a] & sets[b])
        if i and 100 * i >= percent * (len(sets[a]) + len(sets[b]) - i):
            links[a] += 1
            links[b] += 1
            x, y = sorted((find(a), find(b)))
            root[y] = x
    least = {}
    for k, r in enumerate(rows):
        least[find(k)] = min(least.get(find(k), 1 << 60), r[0])
    return sorted((r[0], len(sets[k]), least[find(k)], links[k]) for k, r in enumerate(rows))


@pytest.mark.parametrize(("n", "percent", "block"), [(3, 90, 1024), (5, 80, 1024), (3, 50, 3), (1, 80, 2)])
def test_ngram_join_is_exact(docs, rows, n, percent, block):
    rule = ngram_join.Rule(n, percent, block_sets=block)
    got = sorted((r.doc_id, r.n_shingles, r.component_id, r.n_links) for r in ngram_join.linked_documents(docs, rule).collect())
    assert got == brute_components(rows, n, percent)


def test_prefixes_meet_for_all_linked_sets():
    rng = random.Random(7)
    for _ in range(3000):
        rule = ngram_join.Rule(3, rng.choice([50, 80, 90, 95]))
        base = {rng.getrandbits(64) for _ in range(rng.randint(1, 60))}
        other = set(base)
        for _ in range(rng.randint(0, 6)):
            if rng.random() < 0.5 and len(other) > 1:
                other.remove(rng.choice(sorted(other)))
            else:
                other.add(rng.getrandbits(64))
        if other != base and 100 * len(base & other) >= rule.percent * len(base | other):
            held = {x: rng.randint(1, 3) for x in base | other}  # any count gives an order
            prefixes = []
            for s in (base, other):
                keys = ngram_join.ranked_part(np.array(sorted(s), np.uint64), rule).tolist()
                keys.sort(key=lambda x: (x >= rule.head, held[x] if x < rule.head else 0, x))
                prefixes.append(set(keys[: rule.prefix(len(s))]))
            assert prefixes[0] & prefixes[1]


def test_ngram_join_without_broadcasts_and_with_hot_ngrams(spark):
    rng = random.Random(17)
    phrase = " ".join(f"common{k}" for k in range(12))
    rows = [(k, " ".join([*(f"u{k}x{j}" for j in range(8)), phrase])) for k in range(2600)]
    rows += [(5000 + k, " ".join([phrase, phrase.upper(), *(rng.choice("abc") for _ in range(2))])) for k in range(40)]
    rows += [(None, "only null ids here now"), (None, "only null ids here now"), (7000, rows[3][1]), (7001, rows[3][1] + " tail")]
    rule = ngram_join.Rule(3, 80, broadcast_rows=0)
    got = sorted(((r.doc_id if r.doc_id is not None else -1, r.n_shingles, r.component_id if r.component_id is not None else -1, r.n_links) for r in ngram_join.linked_documents(spark.createDataFrame(rows, "doc_id long, text string").repartition(6), rule).collect()))
    want = brute_components([(-1 if k is None else k, t) for k, t in rows if k is None or k >= 5000 or k in (3, 4)], 3, 80)
    assert [r for r in got if r[0] in {x[0] for x in want}] == want
    assert all(r[2] == r[0] and r[3] == 0 for r in got if 4 < r[0] < 2600)


def test_ngram_join_edges(spark, docs):
    assert ngram_join.linked_documents(docs.filter("false")).count() == 0
    odd = spark.createDataFrame([(None, "a b c d"), (5, "a b c d"), (5, "q r s t u"), (None, "lone words here now"), (None, None)], "doc_id long, text string")
    got = sorted((r.doc_id or 0, r.component_id or 0) for r in ngram_join.linked_documents(odd, ngram_join.Rule(3, 90)).collect() if r.n_shingles)
    assert got == [(0, 0), (0, 5), (5, 5), (5, 5)]
    kept = ngram_join.first_of_each_group(odd, ngram_join.Rule(3, 90))
    assert kept.columns == odd.columns


def test_components_of_a_path_and_a_star(spark):
    edges = [(k, k + 1) for k in range(40)] + [(1000, 1000 + k) for k in range(1, 50)] + [(7, 7)]
    for one_task in (0, 10_000):
        got = dict(ngram_join.components(spark.createDataFrame(edges, "a long, b long"), one_task).collect())
        assert got == {k: 0 for k in range(41)} | {1000 + k: 1000 for k in range(50)}


def brute_substring(rows, span):
    words = [re.findall(r"[^\x20\x09-\x0D]+", r[1] or "") for r in rows]
    seen = Counter(tuple(w[i : i + span]) for w in words for i in range(len(w) - span + 1))
    out = []
    for r, w in zip(rows, words, strict=True):
        gone = {i + k for i in range(len(w) - span + 1) if seen[tuple(w[i : i + span])] > 1 for k in range(span)}
        kept = [x for k, x in enumerate(w) if k not in gone]
        out.append((r[0], len(w), len(gone), hashlib.sha256(" ".join(kept).encode()).hexdigest()))
    return sorted(out)


@pytest.mark.parametrize("plan", [substring_dedup.Plan(), substring_dedup.Plan(35, 18, (9, 18), 1, 3000), substring_dedup.Plan(5, 3, (2, 4), 1, 2000), substring_dedup.Plan(3, 3, (1, 2), 3, 500), substring_dedup.Plan(4, 1, (1, 1), 2, 500)])
def test_substring_dedup_is_exact(docs, rows, plan):
    got = sorted((r.doc_id, r.n_words, r.n_removed, r.kept_sha256) for r in substring_dedup.remove_repeats(docs, plan).collect())
    assert got == brute_substring(rows, plan.span)


def test_substring_dedup_edges(spark, docs):
    assert substring_dedup.remove_repeats(docs.filter("false")).count() == 0
    text = " ".join(f"t{k}" for k in range(40))
    same = spark.createDataFrame([(1, text), (1, text), (None, "short"), (None, text + " tail")], "doc_id long, text string")
    assert sorted((r.n_words, r.n_removed, r.kept) for r in substring_dedup.remove_repeats(same).collect()) == [(1, 0, "short"), (40, 40, ""), (40, 40, ""), (41, 40, "tail")]


def brute_ppm(train, text, method, order):
    """Pretrained, straight from the definition."""
    counts = [{} for _ in range(order + 1)]
    for t in train:
        data = b"\xff" * order + t + b"\xff"
        for i in range(order, len(data)):
            for k in range(order + 1):
                node = counts[k].setdefault(data[i - k : i], Counter())
                node[data[i]] += 1
    data, total = b"\xff" * order + text + b"\xff", 0.0
    for i in range(order, len(data)):
        p, excluded = 1.0, set()
        for k in range(order, -1, -1):
            node = {b: n for b, n in counts[k].get(data[i - k : i], {}).items() if b not in excluded}
            t, d = sum(node.values()), len(node)
            if not t:
                continue
            if data[i] in node:
                n = node[data[i]]
                p *= {"A": n / (t + 1), "C": n / (t + d), "D": (n - 0.5) / t}[method]
                break
            p *= {"A": 1 / (t + 1), "C": d / (t + d), "D": d / (2 * t)}[method]
            excluded |= node.keys()
        else:
            p /= 256 - len(counts[0].get(b"", {}))
        total += math.log10(p)
    return total


@pytest.mark.parametrize(("method", "order"), [("A", 3), ("C", 4), ("D", 2), ("C", 7)])
def test_ppm_matches_its_definition(spark, method, order):
    rows = [r[:2] for r in corpus(3, 40)] + [(950, "é ü ö quite other bytes \x00\x01")]
    df = spark.createDataFrame(rows, "doc_id long, text string").repartition(3)
    low = lambda t: (t or "").encode().lower()
    held = {k: zlib.crc32(str(k).encode()) % 5 == 1 for k, _ in rows}
    train = [low(t) for k, t in rows if not held[k]]
    tokens = Counter(w for t in train for w in [*t.split(), "end"])
    total, distinct = sum(tokens.values()), len(tokens)
    got = {r.doc_id: r for r in ppm.score_documents(df, method, order, bucket_bytes=1500).collect()}
    assert len(got) == len(rows)
    for k, t in rows:
        if len(t or "") > 3000:
            continue
        w = [*low(t).split(), "end"]
        r = got[k]
        assert (r.held_out, r.n_tokens, r.n_known, r.train_tokens) == (held[k], len(w), sum(x in tokens for x in w), total)
        assert r.base_score == pytest.approx(sum(math.log10((tokens[x] + 0.5) / (total + 0.5 * (distinct + 1))) for x in w), rel=1e-9)
        assert r.score == pytest.approx(brute_ppm(train, low(t), method, order), rel=1e-5)


def test_ppm_edges(spark, docs):
    assert ppm.score_documents(docs.filter("false")).count() == 0
    one = spark.createDataFrame([(None, "abc")], "doc_id long, text string")
    assert ppm.score_documents(one).first().score == pytest.approx(4 * math.log10(1 / 256), rel=1e-6)
    # a distribution: the probabilities of all bytes after a context sum to one
    rng = np.random.default_rng(0)
    grams = np.unique(rng.integers(0, 4, 300) << 24 | rng.integers(0, 3, 300) << 16 | 7 << 8 | rng.integers(0, 9, 300)).astype(np.uint32)
    every = np.unique(np.concatenate([(grams & ~np.uint32(255)) | np.uint32(s) for s in range(256)]))
    counts = np.zeros(len(every), np.int64)
    counts[np.searchsorted(every, grams)] = rng.integers(1, 9, len(grams))
    pairs = np.zeros((256, 256), np.int64)
    np.add.at(pairs, ((every >> 8) & 255, every & 255), counts)
    for method in "ACD":
        p = 10.0 ** ppm.code_lengths(every, counts, pairs, method, 3)
        assert np.bincount(np.unique(every >> 8, return_inverse=True)[1], p) == pytest.approx(1)


def test_ppm_contexts_of_five_bytes(spark):
    # what five bytes tell apart, four do not
    rows = [(k, "a12345x b23456y " * 20 if k % 2 else "c12345z d23456w " * 20) for k in range(40)]
    df = spark.createDataFrame(rows, "doc_id long, text string")
    train = [t.encode() for k, t in rows if zlib.crc32(str(k).encode()) % 5 != 1]
    got = {r.doc_id: r.score for r in ppm.score_documents(df).collect()}
    for k in (0, 1):
        assert got[k] == pytest.approx(brute_ppm(train, rows[k][1].encode(), "D", 5), rel=1e-5)
        assert got[k] > brute_ppm(train, rows[k][1].encode(), "D", 4) + 1


def test_ppm_runs_of_contexts_do_not_show():
    grams, sizes = ppm._grams([b"the old mill by the river and the new hill " * 3, b"another text of words"], 5)
    every, total = np.unique(grams, return_counts=True)
    one, _ = ppm._grams([b"the old mill by the river and the new hill " * 3, b"another text of words"], 1)
    pairs = np.bincount(one.astype(np.int64), minlength=1 << 16).reshape(256, 256)
    whole = ppm.code_lengths(every, total, pairs, "D", 5)
    for room in (1, 20, 1 << 19):
        assert ppm._by_contexts(every, total, pairs, "D", 5, room) == pytest.approx(whole, rel=1e-6)


def test_ppm_adaptive_learns(spark):
    a, b = ppm.adaptive_log10(b"abcabcabcabc"), ppm.adaptive_log10(b"qwertzuiopas")
    assert b < a < 0
    df = spark.createDataFrame([(1, "ABCabcabcabc"), (2, None)], "doc_id long, text string")
    got = dict(ppm.adaptive_scores(df).collect())
    assert got[1] == pytest.approx(a) and got[2] == pytest.approx(math.log10(1 / 256))


def brute_chat(turns, budget):
    """conv_id -> (turns, loss text, [tokens], characters), window by window."""
    out = {}
    for conv, group in itertools.groupby(sorted(turns, key=lambda r: (r[0] is not None, r[0] or 0, r[1] is not None, r[1] or 0, r[2] or "", r[3] or "")), key=lambda r: r[0]):
        rows = [(r[2] or "", r[3] or "") for r in group]
        cost = [(len(t) + 3) // 4 + budget.per_turn for _, t in rows]
        before = [sum(cost[:k]) for k in range(len(rows))]
        system = rows[0][0] == "system"
        stride = max(budget.history, (budget.tokens - budget.history - max(budget.system, cost[0] if system else 0)) // 2)
        key = [(sum(c > stride for c in cost[:k]), cost[k] > stride, -1 if cost[k] > stride else before[k] // stride) for k in range(len(rows))]
        esc = lambda x: re.sub(r"([\\<|])", r"\\\1", x)
        fmt = lambda r: f"<|{esc(r[0])}|>{esc(r[1])}<|end|>"
        windows = []
        for _, span in itertools.groupby(range(len(rows)), key=lambda k: key[k]):
            span = list(span)
            head = [0] if system and span[0] > 0 else []
            head += [k for k in range(system, span[0]) if before[k] >= before[span[0]] - budget.history]
            fits = max(cost[k] for k in span) <= stride and (not system or cost[0] + 3 * budget.history <= budget.tokens)
            windows.append(("".join(fmt(rows[k]) for k in head + span), len(head), sum(cost[k] for k in head + span), fits))
        out[conv] = rows, windows
    return out


def test_chat_windows(spark):
    rng = random.Random(9)
    turns = []
    for conv in (1, 2, 3, 4, None):
        for k in range(rng.choice([1, 5, 40])):
            role = "system" if k == 0 and conv in (1, 2, 3) else rng.choice(["user", "assistant"])
            text = "".join(rng.choice("ab <|\\end>$1é\n") for _ in range(rng.choice([0, 5, 60, 200, 900])))
            turns.append((conv, k, role, text))
    turns += [(7, None, None, None), (7, 0, "assistant", "same"), (7, 0, "assistant", "same"), (8, 0, "a|>b\\", "<|end|>"), (9, 300, "assistant", "late"), (9, 2, "user", "early"), (-7, 0, "user", "</s>[INST] ok [/INST]"), (-7, 1, "assistant", "</s>[INST] ok [/INST]")]
    df = spark.createDataFrame([(*t, 1) for t in turns], "conv_id long, turn long, role string, text string, cost int").repartition(3)
    budget = chat_windows.Budget(tokens=120, history=20, system=30, block=4)
    made = chat_windows.chat_windows(df, budget)
    want = brute_chat(turns, budget)
    got = {}
    for r in made.collect():
        got.setdefault(r.conv_id, []).append(r)
    assert got.keys() == want.keys()
    for conv, (rows, windows) in want.items():
        assert [(r.formatted, r.n_repeated, r.tokens) for r in sorted(got[conv], key=lambda r: r.first_turn)] == [w[:3] for w in windows]
        assert all(tokens <= budget.tokens or not fits for _, _, tokens, fits in windows)
    for r in chat_windows.read_back(made).collect():
        rows, windows = want[r.conv_id]
        loss = "".join(t for role, t in rows if role == "assistant")
        sha = lambda s: hashlib.sha256(s.encode()).hexdigest()
        assert (r.n_turns, r.turns_sha256) == (len(rows), sha("".join(f"{a}\n{b}\n" for a, b in rows)))
        assert (r.loss_chars, r.loss_sha256, r.formatted_chars) == (len(loss), sha(loss), sum(len(w[0]) for w in windows))
    assert chat_windows.read_back(chat_windows.chat_windows(df.filter("false"))).count() == 0


def brute_leaks(rows, items, seeds):
    words = lambda t: [w for w in re.split(r"[\W_]+", (t or "").lower()) if w]
    out = set()
    for k, text in rows:
        d = words(text)
        for item, t in items:
            q = words(t)
            if len(q) < seeds.least:
                continue
            need = min(seeds.window, len(q))
            for shift in range(-len(q) + 1, len(d)):
                same = [q[j] == d[j + shift] for j in range(max(0, -shift), min(len(q), len(d) - shift))]
                hit = any(j + max(m) < len(same) and all(same[j + o] for o in m) for m in seeds.masks for j in range(len(same)))
                if hit and any(100 * sum(same[j : j + need]) >= seeds.percent * need for j in range(len(same) - need + 1)):
                    out.add((k, item))
    return out


def test_decontamination(spark):
    rng = random.Random(11)
    vocabulary = [f"v{chr(97 + k % 26)}{chr(97 + k // 26)}" for k in range(200)]
    items = [(k, " ".join(rng.choice(vocabulary) for _ in range(rng.choice([5, 9, 20, 40])))) for k in range(20)] + [(50, None), (51, "")]
    rows = []
    for k in range(60):
        w = [rng.choice(vocabulary) for _ in range(rng.choice([0, 10, 80]))]
        if k % 2:
            q = items[k % 20][1].split()
            for _ in range(rng.randint(0, 5)):
                q[rng.randrange(len(q))] = "changed"
            w[len(w) // 2 : len(w) // 2] = q
        rows.append((k, ", ".join(w)))
    rows += [(70, None), (71, ""), (None, items[3][1]), (1, rows[1][1])]
    docs = spark.createDataFrame([(*r, "x") for r in rows], "doc_id long, text string, item_id string").repartition(3)
    bench = spark.createDataFrame(items, "item_id long, text string")
    seeds = decontamination.Seeds()
    got = [(r.doc_id, r.item_id) for r in decontamination.contaminated_pairs(docs, bench, seeds).collect()]
    want = brute_leaks(rows, items, seeds)
    assert len(got) == len(set(got)) and set(got) == want and len(want) > 10
    shuffled = decontamination.contaminated_pairs(docs, bench, decontamination.Seeds(broadcast_rows=0))
    assert {(r.doc_id, r.item_id) for r in shuffled.collect()} == want
    kept = decontamination.without_contaminated(docs, bench)
    bad = {k for k, _ in want}
    assert sorted(r.doc_id or -1 for r in kept.collect()) == sorted(k or -1 for k, _ in rows if k not in bad) and kept.columns == docs.columns
    assert decontamination.contaminated_pairs(docs.filter("false"), bench).count() == 0
    assert decontamination.contaminated_pairs(docs, bench.filter("false")).count() == 0


def test_masks_miss_no_accepted_placement():
    seeds = decontamination.Seeds()
    for n in range(seeds.least, seeds.window + 1):
        spare = max(e for e in range(n) if 100 * (n - e) >= seeds.percent * n)
        for gone in itertools.combinations(range(n), spare):
            assert any(not {i + o for o in m} & set(gone) for m in seeds.masks for i in range(n - max(m))), (n, gone)


def test_decontamination_without_regard_to_masks(spark):
    rng = random.Random(12)
    items = [(n, " ".join(f"i{n}w{k}x" for k in range(n))) for n in (8, 9, 10, 11, 12, 13, 30)]
    rows, want = [], set()
    for n, text in items:
        need = min(13, n)
        for e in range(6):
            for _ in range(12):
                part = text.split()[:need]
                for k in rng.sample(range(need), e):
                    part[k] = "changed"
                rows.append((len(rows), " ".join(["before", "it", *part, "and", "after"])))
                if 100 * (need - e) >= 75 * need:
                    want.add((rows[-1][0], n))
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    bench = spark.createDataFrame(items, "item_id long, text string")
    got = {(r.doc_id, r.item_id) for r in decontamination.contaminated_pairs(docs, bench).collect()}
    assert got == want


def test_pipeline_matches_brute_force(spark, tmp_path):
    rng = random.Random(13)
    vocabulary = [f"{a}{b}{c}" for a in "bdfg" for b in "aeiou" for c in "lmnrst"]
    text = lambda n: " ".join(rng.choice(vocabulary) for _ in range(n))
    items = [(k, text(30)) for k in range(3)]
    base = [text(120) for _ in range(12)]
    rows = [(k, t, "en", "s", len(t)) for k, t in enumerate(base)]
    rows += [(20, base[0] + " more", "en", "s", 0), (21, base[1], "en", "s", 0), (22, text(60) + " " + items[1][1], "en", "s", 0), (23, "short", "en", "s", 5), (24, None, None, None, None), (25, "la la " * 100, "en", "s", 0), (26, text(80) + " mail a.b@c.example now", "en", "s", 0)]
    spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long").write.parquet(f"{tmp_path}/documents.parquet")
    spark.createDataFrame(items, "item_id long, text string").write.parquet(f"{tmp_path}/benchmark.parquet")
    kept = [r for r in rows if len((r[1] or "").split()) >= 50 and r[0] != 25]
    first = {c for _, _, c, _ in brute_components(kept, 5, 80)}
    kept = [r for r in kept if r[0] in first]
    leaks = {k for k, _ in brute_leaks([r[:2] for r in kept], items, decontamination.Seeds())}
    kept = [(r[0], pii.mask(r[1], pii.detect(r[1]))) for r in kept if r[0] not in leaks]
    got = corpus_pipeline.run(spark, str(tmp_path)).collect()
    tok = packing.tokenizer()
    want = {k: len(tok.encode(t)) + 1 for k, t in kept}
    assert {r.doc_id: r.doc_tokens for r in got} == want and sum(r.length for r in got) == sum(want.values())
    assert 22 not in want and 20 not in want and 21 not in want and 26 in want
    docs = spark.read.parquet(f"{tmp_path}/documents.parquet")
    for _, stage in corpus_pipeline.STAGES[:-1]:
        assert stage(spark, docs, str(tmp_path)).columns == docs.columns
        assert stage(spark, docs.filter("false"), str(tmp_path)).count() == 0
    assert quality_rules.filter_documents(docs).count() == 16


def test_words_are_hashed_by_lanes():
    """Words as bytes.split() gives them: equal ones get one hash, different ones different hashes, whatever their length."""
    from segcompare.llm.words import hashed_words

    draw = random.Random(5)
    pieces = [b"a", b"b", b" ", b"\t", b"\x0b\x0c\r", b"\x1c", b"\x00", b"seven77", b"eight888", "é \xa0".encode(), b"q" * 255, b"q" * 256, b"q" * 257]
    texts = [b"".join(draw.choice(pieces) for _ in range(draw.randint(0, 30))) for _ in range(400)] + [b"", b"  "]
    hashes, sizes = hashed_words(texts)
    assert sizes.tolist() == [len(t.split()) for t in texts]
    known = {}
    for word, value in zip([w for t in texts for w in t.split()], hashes.tolist(), strict=True):
        assert known.setdefault(word, value) == value
    assert len(set(known.values())) == len(known)
    assert [len(x) for x in hashed_words([])] == [0, 0]
