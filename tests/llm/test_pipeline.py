"""The corpus pipeline against a plain version of its stages."""

import collections
import re

import corpus_pipeline as P
from lossgrid.llm import language

SF = "/root/testdata/sf0.001"


def words(text, pattern="[^\\x20\\x09-\\x0D]+"):
    return re.findall(pattern, re.sub("[A-Z]", lambda m: m[0].lower(), text or ""))


def test_stages_in_turn(spark):
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    rows = {r["doc_id"]: r["text"] for r in docs.select("doc_id", "text").collect()}
    out = docs
    for name, stage in P.STAGES[:-1]:
        before = {r["doc_id"] for r in out.select("doc_id").collect()}
        out = stage(spark, out, SF)
        assert out.columns == docs.columns
        kept = {r["doc_id"] for r in out.select("doc_id").collect()}
        assert kept == expected(name, before, rows), name
        out = spark.createDataFrame(out.collect(), docs.schema)
    mixed = P.STAGES[-1][1](spark, out, SF).collect()
    assert {r["doc_id"] for r in mixed} == kept and sum(r["taken"] for r in mixed) > 0
    assert sorted(map(str, P.run(spark, SF).collect())) == sorted(map(str, mixed))


def expected(name, ids, rows):
    if name == "language identification":  # clean documents stay
        return {i for i in ids if any(c.isalpha() for c in rows[i] or "")}
    if name == "exact dedup":
        groups = collections.defaultdict(list)
        for i in ids:
            groups["".join(re.split("[\\x20\\x09-\\x0D]+", rows[i] or ""))].append((-len(rows[i] or ""), i))
        return {min(g)[1] for g in groups.values()}
    if name == "near dedup":
        order = sorted(ids)
        sets = {i: {tuple(w[k : k + 5]) for k in range(max(1, len(w) - 4))} if (w := words(rows[i])) else set() for i in order}
        up = {i: i for i in order}

        def root(x):
            while up[x] != x:
                x = up[x]
            return x

        for n, a in enumerate(order):
            for b in order[:n]:
                if sets[a] and sets[b] and 100 * len(sets[a] & sets[b]) >= 80 * len(sets[a] | sets[b]):
                    x, y = root(a), root(b)
                    up[max(x, y)] = min(x, y)
        return {i for i in order if root(i) == i}
    import pandas as pd

    pattern = "[^\\x00-\\x2F\\x3A-\\x60\\x7B-\\x7F]+"
    windows = set()
    for text in pd.read_parquet(f"{SF}/benchmark.parquet")["text"]:
        w = words(text, pattern)
        windows |= {tuple(w[k : k + 10]) for k in range(max(1, len(w) - 9)) if w}
    sizes = {len(x) for x in windows}
    return {i for i in ids if not any(tuple(w[k : k + n]) in windows for w in [words(rows[i], pattern)] for n in sizes for k in range(len(w) - n + 1))}


def test_rejected_languages(spark):
    docs = spark.createDataFrame([(1, "the house of the hill and the sea", "en", 1), (2, "...", "en", 2), (3, None, "en", 3), (None, "and the sea of the hill", None, 4)], "doc_id long, text string, lang string, score int")
    kept = language.keep_identified(docs, P.LEAST_SCORE)
    assert kept.columns == docs.columns and sorted(r["score"] for r in kept.collect()) == [1, 4]


COLUMNS = "doc_id long, text string, lang string, source string, n_chars long, __key long, __GONE string, __sha string, __id long, __size long"
TEXT = "the house of the hill and the sea was in the town that is by the river and it had been there for as long as anyone knew"


def test_odd_rows_in_every_stage(spark):
    other = "a boat from the other side of the lake came in with the wind and with some people that nobody in the place had seen before"
    leak = spark.read.parquet(f"{SF}/benchmark.parquet").where("length(text) > 200").first()["text"]
    more = (None, 0, 1, "x", "s", 2, 3)
    rows = [
        (1, TEXT, "en", "a", 1, *more[1:2], "x", "s", 2, 3),
        (1, other + " one", "en", "a", 1, 0, "x", "s", 2, 3),  # the same id, another text
        (None, TEXT + " " + other, "en", "b", 1, 0, "x", "s", 2, 3),
        (None, TEXT + " " + other, "en", "b", 1, 0, "x", "s", 2, 3),  # read twice
        (None, leak, "en", None, 1, 0, "x", "s", 2, 3),
        (4, other + " two", "en", "b", 1, 0, "x", "s", 2, 3),  # near the second row
        (5, None, None, None, None, None, None, None, None, None),
        (6, "", "en", "a", 0, 0, "x", "s", 2, 3),
    ]
    docs = spark.createDataFrame(rows, COLUMNS)
    names, out = dict(P.STAGES), docs
    exact_ = names["exact dedup"](spark, docs, SF)
    assert exact_.columns == docs.columns and sorted(r["text"] or "" for r in exact_.collect()) == sorted(["", TEXT, other + " one", other + " two", TEXT + " " + other, leak])
    near = names["near dedup"](spark, docs, SF)
    kept = [r["text"] for r in near.collect()]
    assert near.columns == docs.columns and TEXT in kept and (other + " one" in kept) != (other + " two" in kept)
    clean = names["benchmark decontamination"](spark, docs, SF)
    assert clean.columns == docs.columns and sorted(r["text"] or "" for r in clean.collect()) == sorted(r[1] or "" for r in rows if r[1] != leak)
    for _, stage in P.STAGES[:-1]:
        out = spark.createDataFrame(stage(spark, out, SF).collect(), docs.schema)
    mixed = P.STAGES[-1][1](spark, out, SF).collect()
    assert 0 < len(mixed) == out.count()


def test_empty_table_in_every_stage(spark):
    none = spark.createDataFrame([], COLUMNS)
    for _, stage in P.STAGES:
        assert stage(spark, none, SF).count() == 0


def test_foreign_and_random_letters_go(spark):
    import random

    rng = random.Random(3)
    docs = spark.read.parquet(f"{SF}/documents.parquet").select("doc_id", "text", "lang")
    noise = [(10_000 + k, " ".join("".join(rng.choice("abcdefghijklmnopqrstuvwxyz") for _ in range(rng.randrange(2, 9))) for _ in range(60)), None) for k in range(20)]
    foreign = [(20_000, "Wszyscy ludzie rodzą się wolni i równi pod względem swej godności i swych praw", None), (20_001, "Kaikki ihmiset syntyvät vapaina ja tasavertaisina arvoltaan ja oikeuksiltaan", None)]
    both = docs.unionByName(spark.createDataFrame(noise + foreign, docs.schema))
    kept = {r["doc_id"] for r in language.keep_identified(both, P.LEAST_SCORE).select("doc_id").collect()}
    assert not {i for i in kept if i >= 10_000}
    clean = {r["doc_id"] for r in docs.collect() if any(c.isalpha() for c in r["text"] or "")}
    assert kept == clean
