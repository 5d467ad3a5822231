"""Each operator on small tables: agreement with brute force, and the odd cases."""

import collections
import hashlib
import math
import random
import re
import zlib

import numpy as np
import pytest
from lossgrid.llm import decontaminate, exact, html, language, lines, lm, minhash, mixing, substring, tokens
from lossgrid.llm import queries as Q
from lossgrid.llm import textwords as W
from lossgrid.llm.components import connected_components
from lossgrid.llm.store import Scratch

SPACE = "[^\\x20\\x09-\\x0D]+"
SCHEMA = "doc_id long, text string, lang string, source string, n_chars long, hash string, kept int"
ODD = [
    (None, "no id here but words enough to count", "en", "a", 1, None, None),
    (7, None, None, None, None, "x", 1),
    (8, "", "en", "a", 0, "x", 1),
    (9, " \t\n\r\x0b\x0c ", "en", "a", 0, "x", 1),
    (10, "one", "en", None, 3, "x", 1),
    (11, "One", "fr", "a", 3, "x", 1),
    (12, "ÀÉ x \x1c y É", "fr", "b", 9, "x", 1),
    (12, "ÀÉ x \x1c y É", "fr", "b", 9, "x", 1),
    (13, "word " * 30_000 + "z" * 1_500_000, "en", "b", 1, "x", 1),
]


def prose(rng, n):
    return " ".join(rng.choice(("the", "of", "and", "a", "to")) if rng.random() < 0.4 else f"w{rng.randrange(400)}" for _ in range(n))


def corpus(seed=1, n=60):
    rng = random.Random(seed)
    out = []
    for k in range(n):
        out.append((100 + k, prose(rng, rng.randrange(1, 120)), rng.choice(("en", "fr", None)), rng.choice(("a", "b", "c", None)), 1, "h", 0))
    for k in range(15):
        words = out[k * 3][1].split()
        for _ in range(max(1, len(words) // 12)):
            words[rng.randrange(len(words))] = "changed"
        out.append((300 + k, " ".join(words), "en", "a", 1, "h", 0))
    out += [(400 + k, out[k][1], "en", "b", 1, "h", 0) for k in range(5)]
    out.append((500, "\n".join([out[3][1], out[4][1], "", out[3][1]]), "en", "b", 1, "h", 0))
    return out


@pytest.fixture(scope="module")
def docs(spark):
    return spark.createDataFrame(corpus() + ODD, SCHEMA)


@pytest.fixture(scope="module")
def none(spark):
    return spark.createDataFrame([], SCHEMA)


def words(text):
    return re.findall(SPACE, text or "")


def lowered(text):
    return re.sub("[A-Z]", lambda m: m[0].lower(), text or "")


def everything(df):
    return [r.asDict() for r in df.collect()]


def test_hashes_follow_words():
    import pyarrow as pa

    texts = [t or "" for _, t, *_ in corpus() + ODD]
    for fold in (False, True):
        named, back = {}, {}
        got = W.Words(fold)
        for i, j, hashes, off in got.batches(pa.array([t + "\n" for t in texts])):
            for k in range(i, j):
                mine = hashes[off[k - i] : off[k - i + 1]].tolist()
                want = words(lowered(texts[k]) if fold else texts[k])
                assert len(mine) == len(want)
                for h, w in zip(mine, want, strict=True):
                    assert named.setdefault(h, w) == w and back.setdefault(w, h) == h


def twins(n=1024):
    """Two different words that a sum of powers modulo 2**64 takes for one."""
    bits = [bin(k).count("1") % 2 for k in range(n)]
    return "".join("ab"[b] for b in bits), "".join("ba"[b] for b in bits)


@pytest.mark.parametrize("n", [16, 64, 65, 1024, 2048])
def test_structured_words_differ(n):
    import pyarrow as pa

    a, b = twins(n)
    for lanes in (1, 2):
        (_, _, hashes, _), *_ = W.Words(False, lanes=lanes).batches(pa.array([f"{a} {b} {a}\n"]))
        rows = np.atleast_2d(hashes)
        assert rows.shape == (lanes, 3) and (rows[:, 0] == rows[:, 2]).all() and (rows[:, 0] != rows[:, 1]).all()
    whole = W.Words(True, lanes=2)
    x = whole.text(np.frombuffer(f"A{a} ".encode() + b"z" * (W.BLOCK + 9) + b" end\n", np.uint8))
    y = np.concatenate([whole.text(np.frombuffer(w + b"\n", np.uint8)) for w in (b"a" + a.encode(), b"z" * (W.BLOCK + 9), b"end")], axis=1)
    assert (x == y).all()


def test_structured_words_are_not_copies(spark):
    a, b = twins()
    rest = [f"w{k}" for k in range(40)]
    texts = [" ".join([a, *rest[:34]]), " ".join([b, *rest[:34]]), " ".join([a] * 3), " ".join([b] * 3)]
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    assert {r["n_removed"] for r in everything(substring.repeated_substrings(docs))} == {0}
    near = {r["doc_id"]: r["component_id"] for r in everything(minhash.near_duplicates(docs, 2, 80))}
    assert near[2] == 2 and near[3] == 3
    known = {r["doc_id"]: r["n_known"] for r in everything(lm.language_model_scores(docs.where("doc_id in (2, 3)"), folds=1, held=5))}
    assert known == {2: 4, 3: 4}


def test_banding_follows_the_percentage():
    for percent in (30, 50, 60, 70, 80, 90, 99, 100):
        bands, rows, agree = minhash.plan(percent)
        like = percent / 100
        assert bands * rows <= minhash.BITS and (1 - like**rows) ** bands <= minhash.MISS
        assert agree <= minhash.BITS * (1 + like) / 2
    with pytest.raises(ValueError):
        minhash.plan(3)


def test_links_at_a_low_percentage(spark):
    """Pairs at 0.639 and at 0.58: the first are links at 60 %."""
    rows = []
    for k in range(40):
        shared = [f"s{k}x{j}" for j in range(46)]
        for side, own in enumerate((13, 13)):
            rows.append((2 * k + side, " ".join(shared + [f"o{k}y{side}z{j}" for j in range(own)])))
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    got = {r["doc_id"]: r["component_id"] for r in everything(minhash.near_duplicates(docs, 1, 60))}
    assert got == {i: i - i % 2 for i, _ in rows}


def test_components(spark):
    rng = random.Random(3)
    links = [(rng.randrange(80), rng.randrange(80)) for _ in range(50)] + [(k, k + 1) for k in range(200, 240)] + [(5, 5), (1, 1000)]
    up = {}

    def root(x):
        while up.setdefault(x, x) != x:
            x = up[x]
        return x

    for a, b in links:
        x, y = root(a), root(b)
        up[max(x, y)] = min(x, y)
    got = connected_components(spark.createDataFrame(links, "a long, b long"), Scratch(spark, "cc"), "t")
    linked = {x for a, b in links if a != b for x in (a, b)}
    assert {r["node"]: r["component"] for r in got.collect()} == {x: root(x) for x in linked}
    assert connected_components(spark.createDataFrame([], "a long, b long"), Scratch(spark, "cc"), "e").count() == 0


def brute_near(rows, size, percent):
    sets, out = [], {}
    for i, t, *_ in rows:
        w = words(lowered(t))
        sets.append(frozenset(tuple(w[k : k + size]) for k in range(max(1, len(w) - size + 1))) if w else frozenset())
    up = {i: i for i, *_ in rows}

    def root(x):
        while up[x] != x:
            x = up[x]
        return x

    for a in range(len(rows)):
        for b in range(a):
            if sets[a] and sets[b] and None not in (rows[a][0], rows[b][0]) and 100 * len(sets[a] & sets[b]) >= percent * len(sets[a] | sets[b]):
                x, y = root(rows[a][0]), root(rows[b][0])
                up[max(x, y)] = min(x, y)
    for (i, *_), s in zip(rows, sets, strict=True):
        out[i] = (len(s), root(i) if i is not None else None)
    return out


@pytest.mark.parametrize("size,percent", [(2, 80), (5, 80), (2, 60)])
def test_near_duplicates(spark, docs, size, percent):
    got = {r["doc_id"]: r for r in everything(minhash.near_duplicates(docs, size, percent))}
    want = brute_near(corpus() + ODD, size, percent)
    assert {i: (r["n_shingles"], r["component_id"]) for i, r in got.items()} == want
    assert all(r["kept"] == (r["doc_id"] == r["component_id"] or r["doc_id"] is None) for r in got.values())


@pytest.mark.parametrize("big,block", [(128, 256), (3, 16)])
def test_near_duplicates_in_a_large_group(spark, monkeypatch, big, block):
    """Copies that are mostly, but not all, linked to each other; further stars and the rest are needed."""
    monkeypatch.setattr(minhash, "BIG", big)
    monkeypatch.setattr(minhash, "BLOCK", block)
    rng = random.Random(8)
    base = [f"b{k}" for k in range(60)]
    rows = []
    for k in range(150):
        w = list(base)
        for at in rng.sample(range(60), rng.randrange(0, 9)):
            w[at] = f"x{rng.randrange(10**6)}"
        rows.append((k, " ".join(w)))
    got = {r["doc_id"]: r["component_id"] for r in minhash.near_duplicates(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    assert got == {i: c for i, (_, c) in brute_near(rows, 2, 80).items()}


def test_exact(spark, docs):
    rows = corpus() + ODD
    norm = [re.sub("[\\x20\\x09-\\x0D]", "", t or "") for _, t, *_ in rows]
    best, count = {}, collections.Counter(norm)
    for (i, t, *_), n in zip(rows, norm, strict=True):
        key = (-len(t or ""), i is None, i or 0)
        if n not in best or key < best[n][0]:
            best[n] = (key, i)
    want = sorted((str(i), str(best[n][1]), count[n], hashlib.sha256(n.encode()).hexdigest()) for (i, *_), n in zip(rows, norm, strict=True))
    got = everything(exact.exact_duplicates(docs))
    assert sorted((str(r["doc_id"]), str(r["keep_id"]), r["group_size"], r["text_sha256"]) for r in got) == want
    assert sum(r["kept"] for r in got) == len(count)


def test_digest_index_remembers(spark):
    one = spark.createDataFrame([(1, "a b"), (2, "c")], "doc_id long, text string")
    two = spark.createDataFrame([(3, "ab"), (4, "d"), (5, "d ")], "doc_id long, text string")
    index = exact.DigestIndex(spark, buckets=2)
    assert sorted((r["doc_id"], r["kept"]) for r in exact.exact_duplicates(one, index).collect()) == [(1, True), (2, True)]
    assert sorted((r["doc_id"], r["keep_id"], r["kept"]) for r in exact.exact_duplicates(two, index).collect()) == [(3, 1, False), (4, 5, False), (5, 5, True)]
    assert index.table().count() == 3
    index.drop()


def test_keep_first_keeps_one_of_repeated_rows(spark, docs):
    kept = exact.keep_first(docs)
    assert kept.columns == docs.columns
    texts = [re.sub("\\s", "", r["text"] or "") for r in kept.select("text").collect()]
    assert len(texts) == len({re.sub("[\\x20\\x09-\\x0D]", "", t or "") for _, t, *_ in corpus() + ODD})


ITEMS = [(1, None), (2, ""), (3, "..."), (4, "One"), (None, "changed"), (5, " ".join(corpus()[2][1].split()[:14])), (5, " ".join(corpus()[2][1].split()[:14])), (6, "ÀÉ X")]


def test_contamination(spark, docs):
    items = spark.createDataFrame(ITEMS, "item_id long, text string")
    pattern = re.compile("[^\\x00-\\x2F\\x3A-\\x60\\x7B-\\x7F]+")
    windows = collections.defaultdict(set)
    for i, t in ITEMS:
        w = pattern.findall(lowered(t))
        for k in range(max(1, len(w) - 9)):
            if w:
                windows[tuple(w[k : k + 10])].add(i)
    want = {}
    for i, t, *_ in corpus() + ODD:
        w, hit, found = pattern.findall(lowered(t)), set(), set()
        for n in {len(x) for x in windows}:
            for k in range(len(w) - n + 1):
                if tuple(w[k : k + n]) in windows:
                    hit |= set(range(k, k + n))
                    found |= windows[tuple(w[k : k + n])]
        names = sorted(str(x) for x in found if x is not None)
        want[i] = (len(w), len(hit), len(names), hashlib.sha256(",".join(names).encode()).hexdigest(), bool(hit))
    got = {r["doc_id"]: (r["n_words"], r["n_hit"], r["n_items"], r["items_sha256"], r["contaminated"]) for r in everything(decontaminate.contamination(docs, items))}
    assert got == want
    assert any(x[4] for x in got.values()) and not all(x[4] for x in got.values())


def test_contamination_in_passes(spark, docs, monkeypatch):
    items = spark.createDataFrame(ITEMS, "item_id long, text string")
    before = sorted(map(str, decontaminate.contamination(docs, items).collect()))
    monkeypatch.setattr(decontaminate, "TERMS", 3)
    assert sorted(map(str, decontaminate.contamination(docs, items).collect())) == before


def test_proximity(spark):
    docs = spark.createDataFrame([(1, "alpha x x beta x gamma"), (2, "alpha " + "x " * 50 + "beta gamma"), (3, "gamma beta alpha")], "doc_id long, text string")
    items = spark.createDataFrame([(9, "alpha beta gamma"), (8, "alpha nowhere")], "item_id long, text string")
    got = {(r["item_id"], r["doc_id"]) for r in decontaminate.proximity_matches(docs, items, span=6).collect()}
    assert got == {(9, 1), (9, 3)}


def test_mix(spark, docs):
    got = everything(mixing.mix(docs))
    rows = corpus() + ODD
    assert len(got) == len(rows)
    sizes = collections.Counter()
    for _, t, _, s, *_ in rows:
        sizes[s] += len(words(t))
    order = sorted(sizes, key=lambda s: (s is None, s or ""))
    goal = dict(zip(order, mixing.targets([sizes[s] for s in order], [(3, 1, 2)[k % 3] for k in range(len(order))], 1.5 * sum(sizes.values()), 2), strict=True))
    by = collections.defaultdict(int)
    for r in got:
        assert 0 <= r["taken"] <= 2 * r["size"]
        by[r["target"], r["source_size"]] += r["taken"]
    assert sorted((round(t, 6), n) for t, n in by) == sorted({(round(goal[s], 6), sizes[s]) for s in order})
    for (target, _), taken in by.items():
        assert abs(taken - target) <= max(len(words(t)) for _, t, *_ in rows)
    assert sorted(map(str, got)) == sorted(map(str, everything(mixing.mix(docs.repartition(3)))))


def test_knapsack_is_best():
    rng = random.Random(4)
    for _ in range(60):
        sizes = rng.sample(range(1, 30), 4)
        counts = [rng.randrange(0, 4) for _ in sizes]
        budget = rng.randrange(0, 90)
        take = mixing.knapsack(sizes, counts, budget)
        sums = {0}
        for s, c in zip(sizes, counts, strict=True):
            sums = {x + s * k for x in sums for k in range(c + 1)}
        assert all(0 <= t <= c for t, c in zip(take, counts, strict=True))
        assert sum(s * t for s, t in zip(sizes, take, strict=True)) == max(x for x in sums if x <= budget)


def test_targets():
    assert mixing.targets([10, 10, 1000], [3, 1, 2], 1530, 2).tolist() == [20, 20, 1490]
    assert mixing.targets([], [], 0, 2).tolist() == []


def test_language(spark, docs):
    got = everything(language.identify(docs))
    assert len(got) == len(corpus() + ODD)
    for r in got:
        assert 0 <= r["score"] <= 1
        assert r["held_out"] == (r["doc_id"] is not None and zlib.crc32(str(r["doc_id"]).encode()) % 3 == 1)
        if r["doc_id"] in (7, 8, 9):
            assert (r["lang_pred"], r["score"]) == ("und", 0)
    unlabelled = docs.withColumn("lang", docs["lang"].substr(1, 0)).selectExpr("doc_id", "text", "cast(null as string) as lang")
    assert {r["lang_pred"] for r in language.identify(unlabelled).collect()} == {"und"}


def test_language_on_the_tables(spark):
    from pyspark.sql import functions as F

    sf = "/root/testdata/sf0.01"
    truth = spark.read.parquet(f"{sf}/documents.parquet").select("doc_id", "lang")
    held = Q.op3_language_id(spark, sf).where("held_out").join(truth, "doc_id")
    assert held.agg(F.avg((F.col("lang") == F.col("lang_pred")).cast("int"))).first()[0] > 0.98


def test_out_of_place_by_hand():
    text = "abab ab"
    (_, _, owner, grams, counts), *_ = language.counted([text])
    padded, want = " abab ab ", collections.Counter()
    for n in (1, 2, 3):
        for k in range(len(padded) - n + 1):
            g = padded[k : k + n]
            if g.strip() and " " not in g[1:-1]:
                want[g] += 1
    assert sorted(counts.tolist()) == sorted(want.values())


def brute_substring(rows, window):
    seen = collections.Counter()
    for _, t, *_ in rows:
        w = words(t)
        for k in range(len(w) - window + 1):
            seen[tuple(w[k : k + window])] += 1
    out = []
    for i, t, *_ in rows:
        w, gone = words(t), set()
        for k in range(len(w) - window + 1):
            if seen[tuple(w[k : k + window])] > 1:
                gone |= set(range(k, k + window))
        kept = " ".join(x for k, x in enumerate(w) if k not in gone)
        out.append((str(i), len(w), len(gone), hashlib.sha256(kept.encode()).hexdigest()))
    return sorted(out)


@pytest.mark.parametrize("window", [35, 12, 6])
def test_substring(spark, window):
    rows = corpus(2) + [r for r in ODD if r[0] != 13]
    got = substring.repeated_substrings(spark.createDataFrame(rows, SCHEMA), window)
    assert sorted((str(r["doc_id"]), r["n_words"], r["n_removed"], r["kept_sha256"]) for r in got.collect()) == brute_substring(rows, window)


def test_substring_in_one_text(spark):
    rows = [(1, "x " * 100), (2, " ".join(f"u{k}" for k in range(40)) + " mid " + " ".join(f"u{k}" for k in range(40))), (3, " ".join(f"v{k}" for k in range(36)))]
    got = substring.repeated_substrings(spark.createDataFrame(rows, "doc_id long, text string"), 35, texts=True)
    assert sorted((str(r["doc_id"]), r["n_words"], r["n_removed"], r["kept_sha256"]) for r in got.collect()) == brute_substring(rows, 35)
    assert {r["doc_id"]: r["kept"] for r in got.collect()}[2] == "mid"


def test_lines(spark, docs):
    rows = sorted(corpus() + [r for r in ODD if r[0] is not None], key=lambda r: r[0])
    seen, want = [], {}
    for i, t, *_ in rows:
        for k, line in enumerate((t or "").split("\n")):
            s = frozenset(words(line))
            if (i, k) in want:
                continue
            want[i, k] = bool(s) and any(100 * len(s & o) >= 80 * len(s | o) for o in seen if o)
            seen.append(s)
    got = {(r["doc_id"], r["line_no"]): r["removed"] for r in lines.similar_lines(docs.where("doc_id is not null")).collect()}
    assert got == want
    assert lines.similar_lines(docs).count() >= len(got)


def test_lines_taken_out(spark):
    docs = spark.createDataFrame([(1, "a b c\nd e f\na b c", 5), (2, "x\nd e f", 6)], "doc_id long, text string, line_no int")
    out = {r["doc_id"]: r["text"] for r in lines.drop_lines(docs, lines.similar_lines(docs)).collect()}
    assert out == {1: "a b c\nd e f", 2: "x"}


def reference_lm(rows, order, model):
    """Token by token with dictionaries of hashes; returns log10 probabilities by text."""
    import pyarrow as pa

    h = W.Words(True)
    state = {int(w): int(s) for w, s in zip(model.words, model.state, strict=True)}
    count = {int(w): int(n) for w, n in zip(model.words, model.counts, strict=True)}
    arcs = [dict(zip(k.tolist(), range(len(k)), strict=True)) for k in model.keys]
    out = []
    for _, t, *_ in rows:
        hashes = [x for _, _, hs, _ in h.batches(pa.array([(t or "") + "\n"])) for x in hs.tolist()] + [int(lm.END)]
        past, total = [model.start], 0.0
        for x in hashes:
            s, done = state.get(x, -1), False
            for size in range(len(arcs), 0, -1):
                if len(past) < size:
                    continue
                node = past[-size]
                for level, nxt in zip(arcs, past[len(past) - size + 1 :], strict=False):
                    node = level.get((node << 21) | nxt, -1) if node >= 0 and nxt >= 0 else -1
                if node < 0:
                    continue
                at = arcs[size - 1].get((node << 21) | s, -1) if s >= 0 else -1
                if at >= 0:
                    total, done = total + model.arcs[size - 1][at], True
                    break
                total += model.left[size - 1][node]
            if not done:
                n = count.get(x, 0)
                total += math.log10((1 - model.unknown) * n / model.total if n else model.unknown)
            past = past + [s]
        out.append(total)
    return out


def test_language_model(spark, docs, monkeypatch):
    monkeypatch.setattr(lm, "GRAM", 2e-3)
    rows = corpus() + ODD[:-1]
    table = spark.createDataFrame(rows, SCHEMA)
    train = [r for r in rows if r[0] is None or zlib.crc32(str(r[0]).encode()) % 7 != 2]
    counts = collections.Counter(w for _, t, *_ in train for w in words(lowered(t)) + ["\n"])
    n, v = sum(counts.values()), len(counts)
    got = lm.language_model_scores(table).collect()
    want = {}
    for i, t, *_ in rows:
        w = words(lowered(t)) + ["\n"]
        want[i] = (len(w), sum(counts[x] > 0 for x in w), n, pytest.approx(sum(math.log10((counts[x] + 1) / (n + v + 1)) for x in w), abs=1e-6))
    assert {r["doc_id"]: (r["n_tokens"], r["n_known"], r["train_tokens"], r["base_score"]) for r in got} == want
    from pyspark.sql import functions as F

    held = F.coalesce(lm.remainder(F.col("doc_id"), 7) == 2, F.lit(False))
    model, _ = lm.train(table.where(~held).select(W.terminated(F.col("text")).alias("text")), Scratch(spark, "t"), 3)
    assert len(model.keys) == 2 and len(model.keys[0]) > 5
    assert {r["doc_id"]: r["score"] for r in got} == {r[0]: pytest.approx(s, abs=1e-6) for r, s in zip(rows, reference_lm(rows, 3, model), strict=True)}
    # every history's distribution sums to 1 over the known words and the unknown one
    for history in range(min(5, model.start)):
        total = 0.0
        for k in range(len(model.words)):
            arc = int(lm._place(model.keys[0], np.array([(history << 21) | int(model.state[k])]))[0]) if model.state[k] >= 0 else -1
            total += 10 ** (model.arcs[0][arc] if arc >= 0 else model.left[0][history] + math.log10((1 - model.unknown) * model.counts[k] / model.total))
        total += 10 ** model.left[0][history] * model.unknown
        assert total == pytest.approx(1, abs=1e-6)


def brute_lm(rows, held):
    """Interpolated absolute discounting over the counts of all bigrams and trigrams."""
    texts = [(i, ["<s>", *words(lowered(t)), "\n"]) for i, t, *_ in rows]
    uni, after = collections.Counter(), collections.defaultdict(collections.Counter)
    for i, w in texts:
        if i not in held:
            uni.update(w[1:])
            for k in range(1, len(w)):
                for n in (1, 2)[:k]:
                    after[tuple(w[k - n : k])][w[k]] += 1
    total, once = sum(uni.values()), sum(n == 1 for n in uni.values())
    unknown = (once + 1) / (total + 2)
    out = {}
    for i, w in texts:
        out[i] = 0.0
        for k in range(1, len(w)):
            p = (1 - unknown) * uni[w[k]] / total if uni[w[k]] else unknown
            for n in (1, 2)[:k]:
                seen = after.get(tuple(w[k - n : k]))
                if seen:
                    size = sum(seen.values())
                    p = max(seen[w[k]] - lm.DISCOUNT, 0) / size + lm.DISCOUNT * len(seen) / size * p
            out[i] += math.log10(p)
    return out


@pytest.mark.parametrize("gram,word,part", [(1e-6, 1e-6, 1 << 20), (1.0, 1e-6, 1 << 20), (1.0, 5e-3, 40)])
def test_language_model_counts_every_ngram(spark, monkeypatch, gram, word, part):
    """As one automaton and in parts, with rare words and with words of several parts."""
    for name, value in {"GRAM": gram, "WORD": word, "PART": part, "FLUSH": 500}.items():
        monkeypatch.setattr(lm, name, value)
    rows = corpus() + ODD[:-1]
    held = {r[0] for r in rows if r[0] is not None and zlib.crc32(str(r[0]).encode()) % 7 == 2}
    got = lm.language_model_scores(spark.createDataFrame(rows, SCHEMA).repartition(3)).collect()
    assert len(got) == len(rows)
    assert {r["doc_id"]: r["score"] for r in got} == {i: pytest.approx(s, abs=1e-6) for i, s in brute_lm(rows, held).items()}


def test_language_model_on_the_tables(spark):
    rows = Q.op7_language_model(spark, "/root/testdata/sf0.01").where("held_out").select("score", "base_score").collect()
    assert sum(r["score"] for r in rows) > sum(r["base_score"] for r in rows)


def brute_pieces(word, scores):
    fallback = min(scores.values()) - 10
    best = [(0.0, 0)] + [None] * len(word)
    for end in range(1, len(word) + 1):
        size = len(word[end - 1].encode("utf-8", "surrogatepass"))
        options = [(best[end - 1][0] + fallback * size, -(best[end - 1][1] + size))]
        options += [(best[k][0] + scores[word[k:end]], -(best[k][1] + 1)) for k in range(end) if word[k:end] in scores]
        top = max(options)
        best[end] = (top[0], -top[1])
    return best[-1][1]


def test_token_counts(spark):
    rng = random.Random(5)
    scores = {"".join(rng.choice("ab▁") for _ in range(rng.randrange(1, 5))): -rng.random() * 9 for _ in range(40)} | {"a": -5.0, "▁": -3.0}
    rows = [(k, " ".join("".join(rng.choice("abcé") for _ in range(rng.randrange(1, 9))) for _ in range(rng.randrange(0, 30)))) for k in range(40)] + [(None, "ab"), (99, None), (98, "a" * 1_200_000 + " b")]
    got = {r["doc_id"]: (r["n_pretokens"], r["n_tokens"]) for r in tokens.token_counts(spark.createDataFrame(rows, "doc_id long, text string"), scores).collect()}
    for i, t in rows[:-1]:
        assert got[i] == (len(words(t)), sum(brute_pieces("▁" + w, scores) for w in words(t)))
    assert got[98][0] == 2


def test_prefixes_are_scored_once():
    trie = tokens.Trie({"a": -1.0, "b": -1.0, "ab": -1.5})
    trie.counts(["abab", "ababa", "abb"])
    assert trie.nodes == 6


@pytest.mark.parametrize(
    "page,text",
    [
        (None, ""),
        ("", ""),
        ("<p>a &amp; b\n  c&nbsp;d</p>", "a & b c d"),
        ("<body><nav>Menu</nav><article><h1>T</h1><p>One<br>two<p>three</article><footer>f</footer>", "T\nOne two\nthree"),
        ("<article><p>Text</p><div class='comments'><p>First!</p></div><aside>x</aside><form><input value=1>Send</form></article>", "Text"),
        ("<article><header><h1>Title</h1></header><p>Body</p></article><div id=sidebar>no</div><header>site</header>", "Title\nBody"),
        ("<main><div class='cookie-notice'>We use cookies</div><p>Body</p><script>var a='<p>no</p>'</script><style>p{}</style></main>", "Body"),
        ("<article><p>unclosed <b>bold <p>next", "unclosed bold\nnext"),
        ("<article>a<br><br>b<!-- c --></article>", "a\nb"),
    ],
)
def test_html(page, text):
    assert html.extract(page) == text


def test_html_without_marks():
    long = "The house that was built by the river is not the one that they have in mind for it, and this is what we had to say on it. " * 3
    page = f"<body><div>Home | <a href=a>About</a></div><h2>Head</h2><div>{long}</div><div>Short one.</div><div>{long}</div><div><a href=b>Link</a></div><div>© 2020</div></body>"
    assert html.extract(page) == f"Head\n{long.strip()}\nShort one.\n{long.strip()}"


def test_html_on_the_tables(spark):
    sf = "/root/testdata/sf0.001"
    bodies = {" ".join(r["text"].split()) for r in spark.read.parquet(f"{sf}/documents.parquet").select("text").collect()}
    pages = Q.op9_html_extraction(spark, sf).collect()
    assert pages and all(" ".join(r["text"].split("\n", 1)[1].split()) in bodies and r["n_chars"] == len(r["text"]) for r in pages)


def test_html_judges_blocks_with_and_without_marks(spark):
    """The same text where the article is a plain part, and link lists and menus by their links."""
    pages = [r["html"] for r in spark.read.parquet("/root/testdata/sf0.01/pages.parquet").select("html").collect()]
    plain = [re.sub(r"<(/?)article\b", r"<\1div", page) for page in pages]
    assert plain != pages
    same = [html.extract(a) == html.extract(b) for a, b in zip(pages, plain, strict=True)]
    assert sum(same) >= 0.99 * len(same)
    long = "Pitkä kertomus kaupungista, jonka halki virtaa leveä joki ja jonka kaduilla kävelee iltaisin paljon väkeä. " * 3
    links = "<ul>" + "".join(f"<li><a href=x>Related story number {k} with a long title that goes on for more than one line of text</a></li>" for k in range(3)) + "</ul>"
    for tag in ("article", "div"):
        assert html.extract(f"<body><div><a href=a>Home</a></div><{tag}><h1>Joki</h1><p>{long}</p>{links}<p>{long}</p></{tag}></body>") == f"Joki\n{long.strip()}\n{long.strip()}"


def test_empty_tables(spark, none):
    items = spark.createDataFrame([], "item_id long, text string")
    for out in (
        decontaminate.contamination(none, items), mixing.mix(none), language.identify(none), exact.exact_duplicates(none), substring.repeated_substrings(none), lines.similar_lines(none),
        lm.language_model_scores(none), tokens.token_counts(none, {"a": -1.0}), minhash.near_duplicates(none), html.main_text(spark.createDataFrame([], "page_id long, url string, html string")),
    ):
        assert out.count() == 0


@pytest.mark.parametrize("name", ["op1_benchmark_decontamination", "op4_exact_dedup", "op5_substring_dedup", "op10_minhash_near_dedup"])
def test_sql_agrees(spark, sf, name):
    import duckdb

    con = duckdb.connect()
    for t in ("documents", "benchmark"):
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{sf}/{t}.parquet'")
    want, got = con.sql(Q.oracle_sql()[name]).df(), Q.queries()[name](spark, sf).toPandas()
    cols = sorted(want.columns)
    assert cols == sorted(got.columns)
    rows = [sorted(map(repr, d[cols].astype(object).itertuples(index=False, name=None))) for d in (got, want)]
    assert rows[0] == rows[1]


def test_each_row_with_an_id_is_a_document(spark):
    """Null and repeated ids: what one text has does not count for another."""
    item = "one two three four five six seven eight nine ten eleven"
    docs = spark.createDataFrame([(None, "clean text"), (None, f"x {item}"), (3, item), (3, "short"), (3, item), (4, "none")], "doc_id long, text string")
    got = sorted((r["doc_id"] is None, r["n_words"], r["n_hit"], r["contaminated"]) for r in decontaminate.contamination(docs, spark.createDataFrame([(1, item)], "item_id long, text string")).collect())
    assert got == [(False, 1, 0, False), (False, 1, 0, False), (False, 11, 11, True), (False, 11, 11, True), (True, 2, 0, False), (True, 12, 11, True)]


def test_copies_of_indexed_texts_are_counted(spark):
    before = {t.name for t in spark.catalog.listTables()}
    index = exact.DigestIndex(spark, "digests_for_counts", buckets=2)
    try:
        exact.exact_duplicates(spark.createDataFrame([(1, "a b")], "doc_id long, text string"), index).collect()
        more = spark.createDataFrame([(2, "ab"), (3, "a  b"), (4, "new")], "doc_id long, text string")
        got = {r["doc_id"]: (r["keep_id"], r["group_size"], r["kept"]) for r in exact.exact_duplicates(more, index).collect()}
        assert got == {2: (1, 3, False), 3: (1, 3, False), 4: (4, 1, True)}
        exact.exact_duplicates(more).collect()
    finally:
        index.drop()
    assert {t.name for t in spark.catalog.listTables()} == before


def test_nothing_but_the_result_is_left(spark, docs, monkeypatch, tmp_path):
    import os

    from lossgrid.sources import scratch

    monkeypatch.setattr(scratch, "shared_folder", lambda spark: str(tmp_path))
    small = docs.where("doc_id < 200").select("doc_id", "text", "source")
    for run in (minhash.near_duplicates, substring.repeated_substrings, mixing.mix, lm.language_model_scores):
        run(small).count()
    left = [sorted(os.listdir(tmp_path / d)) for d in os.listdir(tmp_path)]
    assert len(left) == 4 and all(x == ["result"] for x in left)


def test_budgets_of_large_documents():
    def words_of(sizes, counts, budget):
        return int((np.array(sizes) * mixing.fit(np.array(sizes, np.int64), np.array(counts, np.int64), budget)).sum())

    assert words_of([290_000, 600_000], [1, 1], 300_000) == 290_000
    assert words_of([300_000, 310_000, 320_000], [1, 1, 1], 610_000) == 610_000
    rng = np.random.default_rng(5)
    sizes = np.unique(rng.integers(1_000_000, 9_000_000, 40)) * 3
    budget = int(sizes.sum() * 0.37)
    assert 0 <= budget - words_of(sizes, np.ones(len(sizes), int), budget) < 0.001 * budget
    for _ in range(200):
        sizes = np.unique(rng.integers(1, 30, rng.integers(1, 6)))
        counts, budget = rng.integers(0, 4, len(sizes)), int(rng.integers(1, 120))
        reach = {0}
        for size, n in zip(sizes.tolist(), counts.tolist(), strict=True):
            reach = {x + size * k for x in reach for k in range(n + 1) if x + size * k <= budget}
        took = mixing.knapsack(sizes.tolist(), counts.tolist(), budget)
        assert (sizes * took).sum() == max(reach) and (np.array(took) <= counts).all()


def brute_language(text, profiles):
    """Out-of-place distances with dictionaries of spelled n-grams; of equal counts the smaller hash is first."""
    low = "".join(c.lower()[0] if c.isalpha() else " " for c in text)
    grams = collections.Counter()
    for w in low.split():
        padded = f" {w} "
        for n in range(1, language.LONGEST + 1):
            grams.update(g for k in range(len(padded) - n + 1) if (g := padded[k : k + n]).strip() and " " not in g[1:-1] and not (n > 1 and g[0] == g[-1] == " "))
    order = sorted(grams, key=lambda g: (-grams[g], gram_hash(g)))[: language.TOP]
    far = {}
    for name, places in profiles.items():
        far[name] = sum(abs(places[gram_hash(g)] - k) if gram_hash(g) in places else language.TOP for k, g in enumerate(order))
    best = min(sorted(far), key=lambda x: far[x])
    return best, 1 - far[best] / (language.TOP * len(order))


def gram_hash(g):
    low, key = (1 << 64) - 1, ord(g[0])
    for n, c in enumerate(g[1:], 2):
        key = (key * 0x100000001B3 & low) ^ (ord(c) + (n << 22))
    return int(W.mix64(np.array([key], np.uint64))[0]) & ((1 << 40) - 1)


def test_out_of_place_against_brute_force(spark):
    sf = "/root/testdata/sf0.001"
    docs = spark.read.parquet(f"{sf}/documents.parquet").select("doc_id", "text", "lang")
    extra = [(900_001, "Ünïcödé ÀÉÎ straße 東京 tower the of", None), (900_002, "a", None), (900_003, "the " * 90_000 + "y" * 300_000, None), (900_004, "12 34", None)]
    docs = docs.unionByName(spark.createDataFrame(extra, docs.schema))
    from pyspark.sql import functions as F

    held = F.coalesce(lm.remainder(F.col("doc_id"), 3) == 1, F.lit(False))
    table = language.profiles(docs.where(~held))
    places = {name: dict(zip(rows["gram"], rows["rank"], strict=True)) for name, rows in table.groupby("lang")}
    got = {r["doc_id"]: (r["lang_pred"], r["score"]) for r in language.identify(docs).collect()}
    for i, t, _ in docs.collect():
        if not any(c.isalpha() for c in t or ""):
            assert got[i] == ("und", 0.0)
        else:
            name, score = brute_language(t, places)
            assert got[i] == (name, pytest.approx(score, abs=1e-9)), i


STORY = "<p>The story of the town and the river is told by the people that live in it and by those who had to leave for work.</p>"


@pytest.mark.parametrize("page", ['<article class="post has-comments">{}</article>', '<div class="content ad-free">{}</div>', '<div class="article-share-enabled">{}</div>', '<div class="with-sidebar">{}</div>', '<div class="layout-sidebar"><article>{}</article></div>', '<div id="widget-area"><main>{}</main></div>'])
def test_article_is_not_swallowed_by_its_names(page):
    assert html.extract(page.format(STORY * 3)).count("story") == 3


@pytest.mark.parametrize("name", ["site-footer", "cookie-banner", "ad", "comments", "comment-list", "sidebar-left", "related-posts", "share-buttons", "post-comments", "notice"])
def test_named_parts_are_left_out(name):
    for attr in ("class", "id"):
        assert html.extract(f'<div {attr}="{name}">{STORY}</div><div>{STORY * 3}</div>').count("story") == 3


def test_sentences_stay_whole():
    assert "©" in html.extract(f"<div>{STORY}<p>The photo © by the painter is of the town and of the river that it was made for.</p>{STORY}</div>")
    line = html.extract("<p>Fill in <label>the name</label> of the <math><mi>x</mi></math> axis, which is the one that goes from left to right on the page.</p>")
    assert line.startswith("Fill in the name of the x axis")
    assert html.extract(f"<article><h2>Teaser</h2><p>Read more of it.</p></article><div>{STORY * 6}</div>").count("story") == 6
    other = "<p>" + "Nyelvi szöveg amelyben nincsenek ismert gyakori szavak, mégis hosszú bekezdés marad, mert senki sem tudja miért törölnénk ki. " * 2 + "</p>"
    assert html.extract(f"<div>{other * 3}</div>").count("Nyelvi") == 6


def test_deep_and_long_pages():
    import time

    began = time.process_time()
    assert "story" in html.extract("<div><b>" * 20_000 + STORY + "</i></b></div></span>" * 20_000)
    assert html.extract(f"{STORY}" * 5_000).count("story") == 5_000
    assert time.process_time() - began < 60


def test_lines_of_repeated_ids_and_large_groups(spark, monkeypatch):
    """Texts that share an id are told apart, and hot words give what a plain comparison gives."""
    monkeypatch.setattr(lines, "HOT", 8)
    monkeypatch.setattr(lines, "HOT_ROOT", 1 << 30)
    rng = random.Random(11)
    base = [f"b{k}" for k in range(30)]
    rows = []
    for k in range(120):
        w = list(base)
        for at in rng.sample(range(30), rng.randrange(0, 6)):
            w[at] = f"n{rng.randrange(40)}"
        rows.append((rng.choice([1, 2, 3, 4, None]), " ".join(w) + "\n" + prose(rng, 12)))
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    got = {(r["doc_id"], r["print"], r["line_no"]): r["removed"] for r in lines.similar_lines(docs).collect()}
    prints = {(r[0], r[1]): r[2] for r in docs.selectExpr("doc_id", "text", "xxhash64(text)").collect()}
    order = sorted({(i if i is not None else -(1 << 63), k, prints[i, t] & 0xFFFFFFFF, i, prints[i, t], line) for i, t in rows for k, line in enumerate(t.split("\n"))}, key=lambda r: r[:3])
    seen, want = [], {}
    for _, k, _, i, p, line in order:
        s = frozenset(words(line))
        want[i, p, k] = any(180 * len(s & o) >= 80 * (len(s) + len(o)) for o in seen)
        seen.append(s)
    assert got == want and sum(want.values()) > 50


def test_lines_run_no_python(spark, monkeypatch):
    """Lines are cut and compared by DataFrame functions only; every kind of white space parts words."""

    def refuse(*_, **__):
        raise AssertionError("Python on the executors")

    for name in ("mapInArrow", "mapInPandas"):
        monkeypatch.setattr(type(spark.range(1)), name, refuse)
    rows = [(1, "a b c d e\n\n x"), (2, "e\td\rc\x0bb\x0ca\n   \nx y"), (3, "a b c d e f\nonly here"), (4, None), (5, "a b c d g h\nx")]
    got = lines.line_report(lines.similar_lines(spark.createDataFrame(rows, "doc_id long, text string"))).collect()
    assert {r["doc_id"]: (r["n_lines"], list(r["removed_lines"])) for r in got} == {1: (3, []), 2: (3, [0]), 3: (2, [0]), 4: (1, []), 5: (2, [1])}


def test_lines_keep_levels_out_of_plans(spark):
    """The levels of all classes are in no text of a plan, which the driver keeps, and in no row."""
    docs = spark.createDataFrame([(1, "a b c d e\na b c d f"), (2, "x y\n\nz")], "doc_id long, text string")
    plan = lines._leads(lines._lines(docs), 80)._jdf.queryExecution()
    assert len(plan.toString()) < 100_000
    assert "levels" in plan.analyzed().toString() and "levels" not in plan.optimizedPlan().toString()


def test_lines_long_and_of_other_lengths(spark):
    """Lines of up to 300 words around 80 %: the report of whole documents, the one of lines and a plain comparison
    agree, and bitmaps leave few pairs of long lines that share some words only."""
    rng = random.Random(23)
    vocabulary = [f"v{k}" for k in range(2500)]
    texts = [rng.sample(vocabulary, rng.randrange(150, 260)) for _ in range(150)]
    short = [rng.sample(vocabulary, rng.randrange(2, 30)) for _ in range(60)]
    near = []
    for w in texts[:60] + short:
        gone = rng.randrange(0, len(w) // 4 + 1)
        near.append(w[gone:] if rng.random() < 0.5 else w + [f"x{rng.randrange(10**6)}" for _ in range(gone)])
    every = [" ".join(w) for w in texts + short + near] + ["", "\t "]
    rng.shuffle(every)
    rows = [(k // 4 if k // 4 else None, t) for k, t in enumerate("\n".join(every[i : i + 3]) for i in range(0, len(every), 3))] + [(7, every[0]), (7, every[0])]
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    prints = {(r[0], r[1]): r[2] for r in docs.selectExpr("doc_id", "text", "xxhash64(text)").collect()}
    order = sorted({(-(1 << 63) if i is None else i, k, prints[i, t] & 0xFFFFFFFF, t, line) for i, t in rows for k, line in enumerate(t.split("\n"))})
    seen, gone = [], {}
    for i, k, _, t, line in order:
        s = frozenset(words(line))
        gone.setdefault((i, t), []).extend([k] if s and any(100 * len(s & o) >= 80 * len(s | o) for o in seen) else [])
        seen.append(s)
    want = sorted((i, t.count("\n") + 1, len(g), sorted(g)) for (i, t), g in gone.items())
    assert sum(r[2] for r in want) > 50

    def report(df):
        return sorted((-(1 << 63) if r["doc_id"] is None else r["doc_id"], r["n_lines"], r["n_removed"], list(r["removed_lines"])) for r in df.collect())

    assert report(lines.removed_lines(docs)) == want == report(lines.line_report(lines.similar_lines(docs)))
    leads = lines._leads(lines._lines(docs.where("doc_id > 0")), 80)
    longer = lines._heads(leads.where("n > 140")).drop("hot")
    met = lines._cold_pairs(longer, 80).select("xd", "xk", "yd", "yk").distinct().count()
    assert met < 200  # 3897 with one bitmap of 64 bits
