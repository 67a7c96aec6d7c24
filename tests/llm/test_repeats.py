"""Repeated ids, clashing columns and the like: results that the docstrings define."""

import random
import re

import pytest


def sets_of(text, width):
    w = re.findall(r"[^\x20\x09-\x0D]+", re.sub("[A-Z]", lambda m: m[0].lower(), text or ""))
    return {tuple(w[k : k + width]) for k in range(max(len(w) - width + 1, 1))} if w else set()


def components(rows, width=4, percent=80):
    """Least id reached, where rows of one id are one document."""
    root = {i: i for i, _ in rows}

    def find(i):
        while root[i] != i:
            i = root[i]
        return i

    made = [(i, sets_of(t, width)) for i, t in rows]
    for k, (i, a) in enumerate(made):
        for j, b in made[:k]:
            if a and b and 100 * len(a & b) >= percent * len(a | b):
                x, y = find(i), find(j)
                root[max(x, y)] = min(x, y)
    return {i: find(i) for i, _ in rows}


def test_an_id_of_two_texts_joins_their_groups(spark):
    from tangentia.llm.setsketch import keep_one_of_each, near_duplicates

    a, b = " ".join(f"a{k}" for k in range(30)), " ".join(f"b{k}" for k in range(30))
    rows = [(5, a), (5, b), (7, a), (3, b), (9, "else where nothing is alike")]
    df = spark.createDataFrame(rows, "doc_id long, text string")
    got = {r["doc_id"]: (r["component_id"], r["kept"]) for r in near_duplicates(df, 4).collect()}
    assert got == {5: (3, False), 7: (3, False), 3: (3, True), 9: (9, True)}
    assert sorted(r["doc_id"] for r in keep_one_of_each(df, 4).collect()) == [3, 9]


def test_repeated_ids_equal_brute_force(spark):
    from tangentia.llm.setsketch import keep_one_of_each, near_duplicates

    r = random.Random(11)
    bases = [[f"w{b}x{k}" for k in range(60)] for b in range(12)]
    rows = []
    for _ in range(160):
        w = list(r.choice(bases))
        for _ in range(r.randint(0, 5)):
            w[r.randrange(len(w))] = f"e{r.randrange(10_000)}"
        rows.append((r.randrange(130), " ".join(w)))
    rows += [(i, f"alone {i} " + " ".join(f"s{i}y{k}" for k in range(20))) for i in range(120, 170)]
    df = spark.createDataFrame(rows, "doc_id long, text string")
    want = components(rows)
    found = near_duplicates(df, 4).collect()
    assert len(found) == len(rows)
    assert {x["doc_id"]: x["component_id"] for x in found} == want
    once = [x["doc_id"] for x in keep_one_of_each(df, 4).collect()]
    assert sorted(once) == sorted(i for i, c in want.items() if i == c)


def test_training_time_inverts_the_schedule(spark):
    """Against a numeric inverse of the integral; and the rates of all sources add up to the whole at each time."""
    from pyspark.sql import functions as F

    from tangentia.llm.mixing import source_targets, training_time, words_given

    rows = [(float(w), 1000.0, s) for w in (0, 1, 10, 333, 999) for s in (-1.0, -0.5, -1e-12, 0.0, 0.3, 1.0)]
    df = spark.createDataFrame(rows, "word double, goal double, slope double")
    df = df.withColumn("t", training_time(F.col("word"), F.col("goal"), F.col("slope")))
    for r in df.withColumn("back", words_given(F.col("t"), F.col("goal"), F.col("slope"))).collect():
        low, high = 0.0, 1.0
        for _ in range(60):
            mid = (low + high) / 2
            low, high = (mid, high) if 1000 * ((1 - r["slope"]) * mid + r["slope"] * mid * mid) < r["word"] else (low, mid)
        assert abs(r["t"] - low) < 1e-7 and abs(r["back"] - r["word"]) < 1e-6
    sources = spark.createDataFrame([("a", 900), ("b", 50), ("c", 400), (None, 7), ("d", 0)], "source string, source_size long")
    t = source_targets(sources).collect()
    assert all(-1 <= r["slope"] <= 1 for r in t)
    assert abs(sum(round(r["target"]) * r["slope"] for r in t)) < 1e-6


def test_the_mix_follows_the_weights_over_time(spark, sf_dir):
    """In each tenth of training, a source gives about what the integral of its rate says, and all together a tenth."""
    from tangentia.llm.mixing import curriculum, lay_out

    docs = spark.read.parquet(f"{sf_dir.replace('0.001', '0.01')}/documents.parquet")
    goals = {r["source"]: (round(r["target"]), r["slope"]) for r in lay_out(docs).select("source", "target", "slope").distinct().collect()}
    total, longest = sum(g for g, _ in goals.values()), {}
    given = {}
    for r in curriculum(docs).collect():
        longest[r["source"]] = max(longest.get(r["source"], 0), r["taken"])
        k = (r["source"], min(int(r["position"] * 10), 9))
        given[k] = given.get(k, 0) + r["taken"]
    for s, (goal, slope) in goals.items():
        at = lambda t: goal * ((1 - slope) * t + slope * t * t)
        for k in range(10):
            assert abs(given.get((s, k), 0) - (at((k + 1) / 10) - at(k / 10))) <= 2 * longest.get(s, 0) + 2
    assert abs(sum(given.values()) - total) <= len(goals)


def test_nearest_vectors_of_odd_tables(spark):
    """Null, non-finite and empty vectors take no part; lengths don't mix; repeats, ties and few candidates; many query blocks and shards."""
    from tangentia.llm.topk import top_k

    r = random.Random(4)
    rows = [(i, [r.uniform(-1, 1) for _ in range(4 if i % 3 else 2)]) for i in range(160)]
    rows += [(50, None), (100, [float("nan")] * 4), (150, []), (None, [1.0] * 4), (7, [float("inf")] * 4), (8, [None, 1.0])]
    rows += [(200, [0.5] * 4)] * 9 + [(201, [0.5] * 4)] * 9 + [(250, [3.0] * 7)]
    df = spark.createDataFrame([(i, v, 0, "x") for i, v in rows], "vec_id long, embedding array<double>, score long, shard string")
    plain = [(i, [int(c * 256 // 1) for c in v]) for i, v in rows if i is not None and v and all(c is not None and abs(c) < 1e300 for c in v)]
    want = set()
    for q in {i for i, _ in plain if i % 50 == 0}:
        v = min(([len(x), x] for i, x in plain if i == q))[1]
        best = sorted((-sum(a * b for a, b in zip(v, x)), i) for i, x in plain if i != q and len(x) == len(v))[:5]
        want |= {(q, k + 1, i, -s) for k, (s, i) in enumerate(best)}
    for shard_rows, query_rows in ((16_384, 16_384), (20, 2)):
        assert {tuple(x) for x in top_k(df, shard_rows=shard_rows, query_rows=query_rows).collect()} == want
    assert top_k(df.limit(0)).count() == 0


def test_url_rules_on_an_empty_table_and_clashing_columns(spark):
    from tangentia.llm.urls import judge_urls

    rules = [("Com", "/", "allow"), ("a.com", "/x", "block"), ("\u0130.com", "/", "block")]
    rows = [(1, "http://A.com/xy", "h", "p", "r"), (1, "http://A.com/xy", "h", "p", "r"), (None, None, None, None, None), (2, "x://\u0130.com/", "", "", "")]
    df = spark.createDataFrame(rows, "page_id long, url string, host string, path string, rule string")
    got = sorted(map(tuple, judge_urls(df, rules).collect()), key=str)
    assert got == sorted([(1, "a.com", "/xy", "a.com/x", "block"), (1, "a.com", "/xy", "a.com/x", "block"), (None, "", "", None, "allow"), (2, "\u0130.com", "/", "\u0130.com/", "block")], key=str)
    assert judge_urls(df.limit(0), rules).count() == 0
    assert {r["verdict"] for r in judge_urls(df, []).collect()} == {"allow"}


def test_sanitise_keeps_clashing_columns(spark):
    from tangentia.llm.pii import sanitise

    df = spark.createDataFrame([(1, "write to a@b.com now", "s", "d", 5), (1, "write to a@b.com now", "s", "d", 5), (2, None, None, None, None)], "doc_id long, text string, __spans string, _digest string, n_chars long")
    got = sorted(map(tuple, sanitise(df).collect()))
    assert sorted(got, key=str) == sorted([(1, "write to [EMAIL] now", "s", "d", 20)] * 2 + [(2, None, None, None, None)], key=str)


@pytest.mark.parametrize("beside,want", [(0, ""), (1, ""), (3, "[TERM]"), (9, None)])
def test_terms_are_removed_generalised_or_left_by_their_share(spark, beside, want):
    """A name in 6 texts with one address, and in ``beside`` more without it: alone it tells all of the address, then most, then too little."""
    from tangentia.llm.pii import sanitise

    rows = [(i, f"one{i} Quimby wrote{i} to jane.roe@example.com about{i}") for i in range(6)]
    rows += [(100 + i, f"Quimby stood{i} elsewhere{i}") for i in range(beside)]
    rows += [(1000 + i, f"plain{i} text number{i}") for i in range(600)]
    out = {r["doc_id"]: r["text"] for r in sanitise(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    name = "Quimby" if want is None else want
    assert all(out[i] == t.replace("Quimby", name).replace("jane.roe@example.com", "[EMAIL]") for i, t in rows)
