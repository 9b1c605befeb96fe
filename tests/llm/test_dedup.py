import collections
import hashlib
import random
import re

import numpy as np
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

from skewmap.llm import exactdedup, linededup, setjoin, suffixdedup

SPACE = re.compile(r"[\x20\x09-\x0D]+")


# ---------------------------------------------------------------- exact


def test_exact_against_brute_force(documents, texts):
    groups = collections.defaultdict(list)
    for i, t in texts.items():
        groups[SPACE.sub(" ", t or "")].append(i)
    want = {i: (min(g), len(g), i == min(g), hashlib.sha256(t.encode()).hexdigest()) for t, g in groups.items() for i in g}
    got = {r["doc_id"]: tuple(r)[1:] for r in exactdedup.decide(documents).collect()}
    assert got == want


def test_exact_edges(spark, odd_docs):
    got = exactdedup.decide(odd_docs).collect()
    assert len(got) == 12
    by = collections.defaultdict(list)
    for r in got:
        by[r["doc_id"]].append(r)
    assert by[1][0]["keep_id"] == 1 and by[2][0]["keep_id"] == 1 and not by[2][0]["kept"]
    assert by[3][0]["group_size"] == 1
    assert all(r["keep_id"] == 4 and r["group_size"] == 3 and not r["kept"] for r in by[5])
    kept = exactdedup.exact_dedup(odd_docs)
    assert kept.columns == odd_docs.columns and kept.where("doc_id = 5").count() == 0
    assert exactdedup.decide(odd_docs.limit(0)).count() == 0


def test_colliding_digests_are_split_by_bytes(spark, monkeypatch):
    df = spark.createDataFrame([(1, "a"), (2, "b"), (3, "a"), (4, "c c"), (5, "c  c")], "doc_id long, text string")
    monkeypatch.setattr(exactdedup.F, "sha2", lambda c, n: F.lit("ab" * 32) if n == 256 else None)
    got = {r["doc_id"]: (r["keep_id"], r["group_size"]) for r in exactdedup.decide(df).collect()}
    assert got == {1: (1, 2), 2: (2, 1), 3: (1, 2), 4: (4, 2), 5: (4, 2)}


def test_runs_compact_to_the_smallest(spark):
    index = exactdedup.MergeIndex()
    for ids in ([5, 9], [3], [7]):
        index.flush(spark.createDataFrame([(bytearray(b"d"), i, 1) for i in ids], "digest binary, least long, copies long"))
    assert [tuple(r)[1:] for r in index.compact().collect()] == [(3, 4)]


def test_filters_know_their_digests_and_few_others(spark):
    index = exactdedup.MergeIndex(4000)
    make = lambda ids: spark.createDataFrame([(hashlib.sha256(str(i).encode()).digest(), i, 1) for i in ids], "digest binary, least long, copies long")
    index.flush(make(range(2000)))
    index.flush(make(range(1500, 4000)))
    rows = index.lookup(make(range(6000))).select("least", "maybe").collect()
    assert all(r["maybe"][0] for r in rows if r["least"] < 2000) and all(r["maybe"][1] for r in rows if 1500 <= r["least"] < 4000)
    assert sum(r["maybe"][0] for r in rows if r["least"] >= 2000) < 0.05 * 4000
    merged = {r["least"]: r["copies"] for r in index.compact().collect()}
    assert merged == {i: 1 + (1500 <= i < 2000) for i in range(4000)}


def test_exact_rows_of_null_and_repeated_identifiers(spark):
    df = spark.createDataFrame([(0, "a"), (3, "a"), (3, "zzz"), (5, "q"), (5, "q"), (None, "a"), (None, "n"), (None, "n")], "doc_id long, text string")
    got = sorted(((r["doc_id"], r["keep_id"], r["group_size"], r["kept"]) for r in exactdedup.decide(df).collect()), key=str)
    assert got == sorted([(0, 0, 3, True), (3, 0, 3, False), (3, 3, 1, True), (5, 5, 2, True), (5, 5, 2, False), (None, 0, 3, False), (None, None, 2, True), (None, None, 2, False)], key=str)
    assert sorted(map(tuple, exactdedup.exact_dedup(df).collect()), key=str) == sorted([(0, "a"), (3, "zzz"), (5, "q"), (None, "n")], key=str)


def test_exact_plan_is_native(documents):
    text = exactdedup.decide(documents)._jdf.queryExecution().executedPlan().toString()
    assert "Python" not in text and "Arrow" not in text


# ---------------------------------------------------------------- lines


def line_brute(rows, window=linededup.WINDOW, least=linededup.MIN_WORDS, long=linededup.LONG_WORDS):
    """Lines that lie in a run that repeats an earlier place and is wide enough; every earlier place is tried."""
    docs = {i: [(x.strip(" \t\r") or None) for x in (t or "").split("\n")] for i, t in rows}
    words = {i: [len(re.findall(r"[^\x20\x09-\x0D]+", x)) for x in (t or "").split("\n")] for i, t in rows}
    places = collections.defaultdict(list)
    for i in sorted(docs):
        for j, x in enumerate(docs[i]):
            if x:
                places[x].append((i, j))
    gone = collections.defaultdict(set)
    for i, lines in docs.items():
        for j, x in enumerate(lines):
            for a, b in places.get(x, []):
                if (a, b) >= (i, j):
                    break
                lo, hi = 0, 0
                while j - lo > 0 and b - lo > 0 and lines[j - lo - 1] and lines[j - lo - 1] == docs[a][b - lo - 1]:
                    lo += 1
                while j + hi < len(lines) and b + hi < len(docs[a]) and lines[j + hi] and lines[j + hi] == docs[a][b + hi]:
                    hi += 1
                n = words[i][j - lo : j + hi]
                if (lo + hi >= window or max(n) >= long) and sum(n) >= least:
                    gone[i] |= set(range(j - lo, j + hi))
    return docs, gone


def test_lines_against_brute_force(documents, texts):
    docs, most = line_brute(sorted(texts.items()))
    got = {r["doc_id"]: r for r in linededup.line_dedup(documents).collect()}
    total = sum(map(len, most.values()))
    for i, r in got.items():
        assert r["n_lines"] == len(docs[i])
        assert r["n_removed"] <= len(most[i])  # never a line that is not in a repeat
    # A run is found through its fingerprint's first occurrence; nearly every repeat starts there.
    assert total and sum(r["n_removed"] for r in got.values()) >= 0.9 * total


def test_planted_passage_goes_where_it_repeats(spark):
    rng = random.Random(4)
    line = lambda n: " ".join("".join(rng.choices("abcdefgh", k=5)) for _ in range(n))
    run = [line(9), line(3), line(14), line(8), line(20)]
    one = line(60)
    docs = [(1, "\n".join([line(5), *run, line(7)])), (2, "\n".join([line(9), line(4), *run])), (3, "\n".join([one, line(2)])), (4, "\n".join([line(6), one])), (5, "\n".join(line(8) for _ in range(9))), (6, "\n".join([run[0], line(3)]))]
    df = spark.createDataFrame(docs, "doc_id long, text string")
    got = {r["doc_id"]: (r["n_removed"], r["kept_text"]) for r in linededup.line_dedup(df).collect()}
    assert {i: n for i, (n, _) in got.items()} == {1: 0, 2: 5, 3: 0, 4: 1, 5: 0, 6: 0}
    assert got[2][1] == "\n".join(docs[1][1].split("\n")[:2])


def removed_lines(spark, docs, **options):
    df = spark.createDataFrame(docs, "doc_id long, text string")
    return {r["doc_id"]: (r["n_removed"], r["kept_text"]) for r in linededup.line_dedup(df, **options).collect()}


def test_every_repeat_of_brute_force_goes(spark, documents, texts):
    docs, most = line_brute(sorted(texts.items()))
    got = {r["doc_id"]: r["n_removed"] for r in linededup.line_dedup(documents).collect()}
    assert got == {i: len(most[i]) for i in docs}


def test_lines_of_repeated_and_null_keys(spark):
    line = lambda c: " ".join(f"{c}{k}" for k in range(30))
    a, b, c = line("a"), line("b"), line("c")
    df = spark.createDataFrame([(1, a), (2, a), (2, b), (None, b), (None, c), (7, c + "\n" + a), (9, c), (9, c)], "doc_id long, text string")
    got = sorted(((r["doc_id"], r["n_removed"], r["kept_text"]) for r in linededup.line_dedup(df).collect()), key=str)
    assert got == sorted([(1, 0, a), (2, 1, ""), (2, 0, b), (None, 1, ""), (None, 1, ""), (7, 1, c), (9, 1, ""), (9, 1, "")], key=str)


def test_repeat_with_a_line_that_stands_elsewhere_before(spark):
    word = lambda c: " ".join(f"{c}{k}" for k in range(20))
    kinds = [word(c) for c in "abc"]
    for lone in kinds:  # one of the three has the least hash
        first, last = (x for x in kinds if x != lone)
        run = "\n".join([first, lone, last])
        assert removed_lines(spark, [(1, lone), (5, run), (9, run)]) == {1: (0, lone), 5: (0, run), 9: (3, "")}


@pytest.mark.parametrize("options", [{}, {"window": 3, "min_words": 7, "long_words": 9}])
def test_lines_of_few_kinds_against_brute_force(spark, options):
    rng = random.Random(8)
    kinds = [" ".join(f"k{i}" for _ in range(n)) for i, n in enumerate((1, 1, 2, 3, 5, 8, 13, 26))]
    docs = [(i, "\n".join(rng.choices(kinds, k=rng.randrange(1, 12)))) for i in range(150)]
    lines, gone = line_brute(docs, *([options["window"], options["min_words"], options["long_words"]] if options else []))
    want = {i: (len(gone[i]), "\n".join(x for j, x in enumerate(lines[i]) if j not in gone[i])) for i in lines}
    assert removed_lines(spark, docs, **options) == want


def test_blank_lines_break_no_passage(spark):
    line = lambda c: " ".join(f"{c}{k}" for k in range(20))
    a, b, c, d = map(line, "abcd")
    docs = [(1, f"{d}\n{a}\n\n{b}\n\n{c}"), (2, f"{a}\n\n{b}\n \t\n\x0b\n{c}\nown"), (3, f"\n{a}\n"), (4, f"{b}\n{c}")]
    assert removed_lines(spark, docs) == {1: (0, docs[0][1]), 2: (3, "\n \t\n\x0b\nown"), 3: (0, docs[2][1]), 4: (2, "")}


def test_line_edges(odd_docs):
    got = linededup.line_dedup(odd_docs).collect()
    assert len(got) == 12
    assert {r["doc_id"]: r["n_lines"] for r in got}[1] == 0
    assert [r["kept_text"] for r in got if r["doc_id"] == 2] == [""]
    assert linededup.line_dedup(odd_docs.limit(0)).count() == 0
    long = [r for r in got if r["doc_id"] == 7][0]
    assert long["n_removed"] == 0  # another line, as it has one word more


def test_line_plan_is_native(documents):
    text = linededup.line_dedup(documents)._jdf.queryExecution().executedPlan().toString()
    assert "Python" not in text and "Arrow" not in text


# ---------------------------------------------------------------- byte strings


def bytes_brute(rows, length):
    seen, out = set(), {}
    for i, t in sorted(rows):
        b = (t or "").encode()
        gone = bytearray(len(b))
        for p in range(len(b) - length + 1):
            if (w := b[p : p + length]) in seen:
                gone[p : p + length] = b"\1" * length
            else:
                seen.add(w)
        kept = bytes(x for x, g in zip(b, gone) if not g)
        out[i] = (len(b), sum(gone), (b"\0" + bytes(gone)).count(b"\0\1"), hashlib.sha256(kept).hexdigest())
    return out


@pytest.mark.parametrize("options", [{}, {"chunk": 2, "shard_bytes": 5000}])
def test_bytes_against_brute_force(documents, texts, options):
    got = {r["doc_id"]: tuple(r)[1:] for r in suffixdedup.remove_repeats(documents, **options).collect()}
    assert got == bytes_brute(texts.items(), 100)


@pytest.mark.parametrize("seed", range(3))
def test_small_alphabets_and_short_strings(spark, seed):
    rng = random.Random(seed)
    base = "".join(rng.choices("ab", k=400))
    rows = [(i, base[(a := rng.randrange(300)) : a + rng.randrange(100)] + rng.choice(["", "a" * 60, "é" * 20]) + base[: rng.randrange(50)]) for i in range(40)]
    df = spark.createDataFrame(rows, "doc_id long, text string")
    for chunk in (3, 20_000):
        got = {r["doc_id"]: tuple(r)[1:] for r in suffixdedup.remove_repeats(df, length=16, gram=4, chunk=chunk).collect()}
        assert got == bytes_brute(rows, 16)


def test_slices_of_long_texts(spark, monkeypatch):
    monkeypatch.setattr(suffixdedup, "SLICE", 256)
    rng = random.Random(8)
    t = "".join(rng.choices("abcd", k=3000))
    raw = np.frombuffer(t.encode(), np.uint8)
    whole = [set(), set()]
    for k in (0, 1):
        for a in range(0, len(raw) - 99, 256) if k else [0]:
            part = raw[a : a + 256 + 99] if k else raw
            if not k:
                monkeypatch.setattr(suffixdedup, "SLICE", 1 << 22)
            else:
                monkeypatch.setattr(suffixdedup, "SLICE", 256)
            h, at, first, count = suffixdedup.anchors(part)
            whole[k] |= {(int(x), int(f + a + i)) for x, f, c in zip(h, first, count) for i in range(c)}
    assert whole[0] == whole[1]


def test_bytes_edges(odd_docs):
    got = suffixdedup.remove_repeats(odd_docs, with_text=True).collect()
    by = {r["doc_id"]: r for r in got}
    assert len(got) == 12 and by[1]["n_bytes"] == 0 and by[4]["n_removed"] == 0
    assert by[10]["n_removed"] == 4999 and bytes(by[10]["kept"]) == b"a"
    assert by[7]["n_bytes"] - by[7]["n_removed"] < 120
    assert by[None]["n_removed"] == 0
    assert suffixdedup.remove_repeats(odd_docs.limit(0)).count() == 0


def test_hot_anchors_are_dealt_by_segment(spark, monkeypatch):
    """Texts that all hold one passage at different places: its anchors have many segments."""
    rng = random.Random(12)
    passage = "".join(rng.choices("abcdef ", k=60))
    rows = [(i, "".join(rng.choices("abcdef ", k=rng.randrange(5, 50))) + passage + "".join(rng.choices("abcdef ", k=rng.randrange(5, 50)))) for i in range(120)]
    df = spark.createDataFrame(rows, "doc_id long, text string").repartition(4)
    want = {r["doc_id"]: tuple(r) for r in suffixdedup.remove_repeats(df, length=40, gram=8).collect()}
    monkeypatch.setattr(suffixdedup, "SAMPLED", 1)
    for chunk, most in ((20, 4096), (7, 2), (7, 0)):
        monkeypatch.setattr(suffixdedup, "MOST_HOT", most)
        got = {r["doc_id"]: tuple(r) for r in suffixdedup.remove_repeats(df, length=40, gram=8, chunk=chunk).collect()}
        assert got == want
    assert sum(r[2] for r in want.values()) > 119 * 55


def test_suffix_array_and_common_prefixes():
    rng = np.random.default_rng(2)
    for n, k in ((0, 2), (1, 2), (500, 2), (300, 250), (400, 1)):
        t = rng.integers(0, k, n).astype(np.uint8)
        b = t.tobytes()
        order = suffixdedup.suffix_array(t)
        assert order.tolist() == sorted(range(n), key=lambda i: b[i:])
        if n:
            got = suffixdedup.common_prefixes(t, order, 30)
            want = [0] + [next((j for j in range(30) if j >= n - max(x, y) or b[x + j] != b[y + j]), 30) for x, y in zip(order[:-1].tolist(), order[1:].tolist())]
            assert got.tolist() == want


def test_merge_of_runs():
    runs = [(np.array([b"a" * 16, b"c" * 16]), np.array([5, 1])), (np.array([b"a" * 16, b"b" * 16]), np.array([2, 9])), (np.array([b"c" * 16]), np.array([0]))]
    d, s = suffixdedup.merge_runs(runs)
    assert s.tolist() == [2, 9, 0] and len(d) == 3


# ---------------------------------------------------------------- sets


def sets_brute(rows):
    sets = {i: set(setjoin.shingles((t or "").encode()).tolist()) for i, t in rows}
    up = {i: i for i in sets}

    def find(x):
        while up[x] != x:
            x = up[x]
        return x

    ids = [i for i in sets if sets[i]]
    for x in ids:
        for y in ids:
            if x < y and (c := len(sets[x] & sets[y])) and 100 * c >= 75 * (len(sets[x]) + len(sets[y]) - c):
                a, b = find(x), find(y)
                up[max(a, b)] = min(a, b)
    return {i: (len(s), find(i)) for i, s in sets.items()}


def test_sets_against_brute_force(documents, texts):
    got = {r["doc_id"]: (r["n_shingles"], r["component_id"]) for r in setjoin.components(documents).collect()}
    assert got == sets_brute(texts.items())


def near_rows(seed=3, groups=12):
    """Families of near copies of several sizes, texts that share most of a passage, and lone texts."""
    rng = random.Random(seed)
    word = lambda: "".join(rng.choices("abcdefghij", k=4))
    rows = []
    passage = [word() for _ in range(60)]
    for g in range(groups):
        base = [word() for _ in range(rng.randrange(20, 80))]
        for _ in range(rng.randrange(1, 25)):
            own = list(base)
            for _ in range(rng.randrange(0, 3)):
                own[rng.randrange(len(own))] = word()
            rows.append(" ".join(own))
    rows += [" ".join(passage + [word() for _ in range(rng.randrange(5, 25))]) for _ in range(60)]
    return [(i, t) for i, t in enumerate(rows, 1)]


@pytest.mark.parametrize("hot,tile", [(1000, 20_000), (5, 7), (10**9, 10)])
def test_hot_lists_give_the_same(spark, monkeypatch, hot, tile):
    monkeypatch.setattr(setjoin, "HOT", hot)
    monkeypatch.setattr(setjoin, "TILE", tile)
    monkeypatch.setattr(setjoin, "MANY", 0 if tile == 10 else 10_000)  # pairs are asked in rounds
    rows = near_rows()
    df = spark.createDataFrame(rows, "doc_id long, text string").repartition(5)
    assert {r["doc_id"]: (r["n_shingles"], r["component_id"]) for r in setjoin.components(df).collect()} == sets_brute(rows)


def test_sets_of_repeated_and_null_identifiers(spark):
    text = lambda c, n=40: " ".join(f"{c}{i}" for i in range(n))
    near = text("a") + " end"
    rows = [(1, text("a")), (2, near), (2, text("b")), (7, text("b")), (None, text("b")), (None, text("c")), (None, text("c")), (9, None), (9, None)]
    for order in (rows, rows[::-1]):
        df = spark.createDataFrame(order, "doc_id long, text string").coalesce(1)
        got = sorted(((r["doc_id"], r["n_shingles"], r["component_id"]) for r in setjoin.components(df).collect()), key=str)
        assert got == sorted([(1, 36, 1), (2, 37, 1), (2, 36, 2), (7, 36, 2), (None, 36, 2), (None, 36, None), (None, 36, None), (9, 0, 9), (9, 0, 9)], key=str)
        kept = sorted(map(tuple, setjoin.near_dedup(df).collect()), key=str)
        assert kept == sorted([(1, text("a")), (2, text("b")), (None, text("c")), (9, None), (9, None)], key=str)


@pytest.mark.parametrize("seed", range(3))
def test_chains_and_common_passages(spark, seed):
    rng = random.Random(seed)
    word = lambda: "".join(rng.choices("abcdefghijklmnop", k=4))
    common = [word() for _ in range(30)]
    rows, at = [], 0
    for _ in range(12):
        own = [word() for _ in range(rng.randrange(6, 70))]
        for _ in range(rng.randrange(1, 9)):  # each a little further from the first
            own[rng.randrange(len(own))] = word()
            rows.append((at, " ".join(own + (common if rng.random() < 0.5 else []))))
            at += 1
    rng.shuffle(rows)
    df = spark.createDataFrame(rows, "doc_id long, text string")
    got = {r["doc_id"]: (r["n_shingles"], r["component_id"]) for r in setjoin.components(df).collect()}
    assert got == sets_brute(rows)


def test_set_edges(odd_docs):
    got = setjoin.components(odd_docs).collect()
    by = {r["doc_id"]: (r["n_shingles"], r["component_id"]) for r in got}
    assert len(got) == 12
    assert by[1] == (0, 1) and by[2] == (0, 2) and by[3] == (0, 3)
    assert by[4] == (1, 4) and by[5] == (1, 4)
    assert by[7][1] == 6 and by[None][1] is None
    assert setjoin.components(odd_docs.limit(0)).count() == 0


def test_components_of_chains(spark):
    edges = spark.createDataFrame([(i, i + 1) for i in range(60)] + [(100, 101), (200, 200)], "a long, b long")
    got = {r["id"]: r["component"] for r in setjoin.connected(edges).collect()}
    assert {got[i] for i in range(61)} == {0} and got[101] == 100 and got[200] == 200


def test_sets_are_cut_by_columns():
    rng = random.Random(8)
    letters = ["a", "B", "é", " ", " ", "\t", "\x0b", "\n"]
    texts = ["", None, " ", "x" * 200 + " Y", *("".join(rng.choices(letters, k=rng.randrange(1, 400))) for _ in range(200)), "w " * 9]
    found, offs = setjoin.shingled(pa.array(texts, pa.string()))
    for i, text in enumerate(texts):
        words = (text or "").encode().lower().split()
        sets = {tuple(words[j : j + 5]) for j in range(max(1, len(words) - 4))} if words else set()
        own = found[offs[i] : offs[i + 1]]
        assert len(own) == len(sets) and own.tolist() == setjoin.shingles((text or "").encode()).tolist()
    words = [bytes([65 + n % 26]) * n for n in range(1, 150)] + [b"a" * 8 + b"\0", b"a" * 8, b"a" * 64 + b"b"]
    hashes, many = setjoin._word_hashes(pa.array(words, pa.binary()))
    assert len(set(hashes.tolist())) == len({w.lower() for w in words}) and many.tolist() == [1] * len(words)


def test_short_lists_give_the_pairs_of_blocks(monkeypatch):
    rng = np.random.default_rng(9)
    n = 4000
    token = np.sort(rng.integers(0, 900, n))
    size, half = rng.integers(20, 60, n), rng.choice([2, 2, 0], 900)[token]
    half = np.where(half == 2, 2, rng.integers(0, 2, n))
    at = size << 24 | rng.integers(0, 12, n)
    batch = pa.RecordBatch.from_arrays([pa.array(c) for c in (token, np.arange(n), at, rng.integers(0, 40, n), half)], ["token", "id", "at", "component", "half"])

    def pairs(short):
        monkeypatch.setattr(setjoin, "SHORT", short)
        return sorted(tuple(r.values()) for b in setjoin._cross_pairs(iter([batch])) for r in b.to_pylist())

    assert pairs(0) == pairs(64) == pairs(4) and len(pairs(64)) > 1000
