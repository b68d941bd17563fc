"""MinHash groups, mixing, language ID, packing, line spread and LM scoring against brute force, with awkward rows."""

import math
import os
import re
import zlib
from collections import Counter

import numpy as np
import pytest
from pyspark.sql import functions as F

from apcube.llm import components, langid, linededup, minhash, mixing, ngramlm, packing

DOC = "doc_id bigint, text string, lang string, source string, n_chars bigint, n bigint, key string, unit int"


def docs_of(spark, rows):
    """rows: (id, text[, lang[, source]]); with extra columns whose names the operators use inside."""
    full = [(r[0], r[1], r[2] if len(r) > 2 else "en", r[3] if len(r) > 3 else "a", len(r[1] or ""), 7, "k", 1) for r in rows]
    return spark.createDataFrame(full, DOC)


def word_rows(seed=0, n=60):
    g = np.random.default_rng(seed)
    base = [" ".join(f"w{x}" for x in g.integers(0, 4000, 120)) for _ in range(n // 3)]
    rows = []
    for i in range(n):
        w = base[i % len(base)].split(" ")
        for _ in range(int(g.integers(0, 8))):
            w[int(g.integers(0, len(w)))] = f"x{g.integers(0, 9999)}"
        rows.append((i * 3 + 1, (" " if i % 2 else "\n").join(w).title() if i % 5 else " ".join(w)))
    return rows + [(1000, None), (1001, ""), (1002, " \t\n"), (1003, "one"), (1004, "ONE"), (1005, "one two"), (1006, rows[0][1]), (1007, rows[0][1])]


def shingles(text, k):
    w = re.findall(r"[^\x20\x09-\x0D]+", re.sub("[A-Z]", lambda m: m[0].lower(), text or ""))
    return {tuple(w[i : i + k]) for i in range(len(w) - k + 1)} if len(w) >= k else ({tuple(w)} if w else set())


def brute_groups(rows, k, num, den):
    sets = {i: shingles(t, k) for i, t in rows}
    up = {i: i for i in sets}

    def root(x):
        while up[x] != x:
            x = up[x]
        return x

    ids = sorted(sets)
    for a in ids:
        for b in ids:
            if a < b and sets[a] and sets[b] and den * len(sets[a] & sets[b]) >= num * len(sets[a] | sets[b]):
                x, y = root(a), root(b)
                up[max(x, y)] = min(x, y)
    return {i: (len(sets[i]), root(i), root(i) == i) for i in ids}


@pytest.mark.parametrize("k,num,den", [(3, 85, 100), (5, 4, 5)])
def test_minhash_equals_brute_force(spark, k, num, den):
    rows = word_rows()
    got = {r["doc_id"]: (r["n_shingles"], r["component_id"], r["kept"]) for r in minhash.near_duplicates(docs_of(spark, rows), k, (num, den)).collect()}
    assert got == brute_groups(rows, k, num, den)


def test_minhash_large_group_and_small_blocks(spark, monkeypatch):
    g = np.random.default_rng(3)
    base = [f"w{x}" for x in g.integers(0, 9999, 100)]
    rows = []
    for i in range(90):
        w = list(base)
        for _ in range(int(g.integers(0, 5))):
            w[int(g.integers(0, 100))] = f"y{g.integers(0, 99999)}"
        rows.append((i, " ".join(w)))
    monkeypatch.setattr(minhash, "BLOCK", 16)
    got = {r["doc_id"]: (r["n_shingles"], r["component_id"], r["kept"]) for r in minhash.near_duplicates(docs_of(spark, rows), 3, (85, 100)).collect()}
    assert got == brute_groups(rows, 3, 85, 100)


def test_minhash_without_ids_or_rows(spark):
    assert minhash.near_duplicates(docs_of(spark, [])).count() == 0
    rows = [(None, "a b c d e f"), (5, "a b c d e f"), (5, "a b c d e f"), (None, None)]
    got = minhash.near_duplicates(docs_of(spark, rows)).collect()
    assert len(got) == 4 and {(r["component_id"], r["kept"]) for r in got if r["doc_id"] == 5} == {(5, True)}
    assert sorted(r["kept"] for r in got if r["doc_id"] is None) == [False, True]
    assert minhash.deduplicate(docs_of(spark, rows)).columns == [c.split()[0] for c in DOC.split(", ")]


def test_banding_misses_little():
    for t in (0.8, 0.85, 0.9):
        b, r = minhash.banding(t)
        assert b * r <= 128 and (1 - t**r) ** b <= 1e-4


def test_components(spark):
    edges = [(i, i + 1) for i in range(0, 40)] + [(100, 101), (101, 100), (7, 7), (None, 3), (200, 150), (150, 170)]
    got = {r["node"]: r["component"] for r in components.components(spark.createDataFrame(edges, "a bigint, b bigint")).collect()}
    assert got == {**{i: 0 for i in range(41)}, 100: 100, 101: 100, 150: 150, 170: 150, 200: 150}
    assert components.components(spark.createDataFrame([], "a bigint, b bigint")).count() == 0


def test_apportion_is_highest_quotients():
    g = np.random.default_rng(1)
    for _ in range(200):
        wants = g.uniform(0, 100, int(g.integers(1, 9))).round(2).tolist()
        seats = int(g.integers(0, 300))
        got, brute = mixing.apportion(wants, seats), [0] * len(wants)
        for _ in range(seats if sum(wants) else 0):
            i = max(range(len(wants)), key=lambda j: (wants[j] / (2 * brute[j] + 1), -j))
            brute[i] += 1
        assert got == brute
    per = mixing.shard_quotas([5, 2, 1], 80, 7)
    assert [sum(x) for x in zip(*per)] == mixing.apportion([5, 2, 1], 80) and all(min(x) >= 0 for x in per)


def test_targets_fill_under_caps():
    assert mixing.targets([10, 100], [5, 2]) == [30, 80]
    assert mixing.targets([0, 0], [5, 2]) == [0, 0]
    assert sum(mixing.targets([1, 5, 900], [5, 2, 1])) == pytest.approx(906)


def test_mix(spark):
    g = np.random.default_rng(5)
    rows = [(i, " ".join(["w"] * int(g.integers(0, 300))), "en", [None, "b", "a", "Z"][int(i % 4 if i % 3 else 2)]) for i in range(300)] + [(900, None, "en", "a"), (None, "x y", "en", "b"), (901, "q " * 20000, "en", "Z")]
    df = docs_of(spark, rows)
    got = mixing.mix(df).collect()
    assert len(got) == len(rows)
    source = {r[0]: r[3] for r in rows}
    size = {r[0]: len(re.findall(r"[^\x20\x09-\x0D]+", r[1] or "")) for r in rows}
    order = ["Z", "a", "b", None]
    sizes = [sum(size[i] for i in size if source[i] == s) for s in order]
    want = mixing.targets(sizes, [5, 2, 1, 5])
    for s, n, t in zip(order, sizes, want):
        mine = [r for r in got if source[r["doc_id"]] == s]
        assert all(r["source_size"] == n and r["target"] == pytest.approx(t) for r in mine)
        assert abs(sum(r["taken"] for r in mine) - t) <= 64
    assert all(r["size"] == size[r["doc_id"]] and 0 <= r["taken"] <= 3 * r["size"] for r in got)
    again = {(r["doc_id"], r["taken"]) for r in mixing.mix(df.repartition(7)).collect()}
    assert again == {(r["doc_id"], r["taken"]) for r in got}
    assert mixing.mix(docs_of(spark, [])).count() == 0
    assert mixing.mixed_documents(df).columns == df.columns


@pytest.mark.parametrize("shard_words", [1 << 22, 1000])
def test_mix_takes_whole_quotas_per_shard(spark, shard_words):
    """Every shard has its seats of every source, of blocks that a seeded order of them gives, by brute force."""
    g = np.random.default_rng(6)
    rows = [(i, "w " * int(g.integers(0, 200)), "en", "abc"[min(2, int(g.integers(0, 6)))]) for i in range(200)]
    df = docs_of(spark, rows)
    got = mixing.mix(df, block=16, shard_words=shard_words).collect()
    source, size = {r[0]: r[3] for r in rows}, {r[0]: r[1].count("w") for r in rows}
    order = sorted(set(source.values()))
    sizes = [sum(size[i] for i in size if source[i] == s) for s in order]
    want = mixing.targets(sizes, [5, 2, 1])
    shards = -(-round(sum(want) / 16) * 16 // shard_words)
    quotas = mixing.shard_quotas(want, round(sum(want) / 16), shards)
    assert all(r["taken"] == sum(x["words"] for x in r["shards"]) for r in got)
    for k in range(shards):
        for s, name in enumerate(order):
            words = sum(x["words"] for r in got for x in r["shards"] if x["shard"] == k and source[r["doc_id"]] == name)
            assert abs(words - 16 * quotas[k][s]) <= 3 * 16  # the short block comes once a round
    parted = [r for r in got if r["taken"] % max(1, r["size"])]
    assert len(parted) > len(order)  # blocks from all over a source, not one run
    walk = mixing.Walk(1003, 16, 700, np.array([20, 44]), "x")
    each = [walk.take(np.array([i]), np.array([1])) for i in range(1003)]
    assert sum(int(w.sum()) for _, _, w in each) == 700 and sorted(walk.place(np.arange(63))) == list(range(63))
    assert walk.take(np.array([0]), np.array([1003]))[2].tolist() == [sum(int(w[k == j].sum()) for _, k, w in each) for j in (0, 1)]


def test_mixed_documents_keeps_rows_without_id_and_clashing_names(spark):
    rows = [(None, "a b c " * 30, "en", "s"), (None, "d e " * 30, "en", "s"), (1, "f " * 50, "en", "s"), (1, "g " * 60, "en", "s"), (2, None, "en", "s")]
    df = docs_of(spark, rows).selectExpr("*", "1 as size", "2 as taken", "'x' as row", "3 as bucket", "4 as h", "5 as `end`")
    got = mixing.mixed_documents(df, weights=(1,)).collect()
    assert got[0].asDict().keys() == set(df.columns) and {r["text"] for r in got} == {r[1] for r in rows[:4]} and {r["row"] for r in got} == {"x"}


def test_languages_are_learned_off_the_driver(spark, monkeypatch):
    """The sample's texts and n-grams never reach the driver, whose memory is small."""
    rows = [(i, "the cat sat on the mat" if i % 2 else "der hund lag auf dem sofa", "en" if i % 2 else "de") for i in range(40)]
    here = langid.train([r[1] for r in rows], [r[2] for r in rows], [i % 4 > 1 for i in range(40)])
    real, driver = langid.train, os.getpid()

    def elsewhere(*args):
        assert os.getpid() != driver
        return real(*args)

    monkeypatch.setattr(langid, "train", elsewhere)
    model = langid.learn(docs_of(spark, rows), F.lit(True), F.col("doc_id") % 4 > 1)
    assert model.langs == ["de", "en"] and (model.table == here.table).all() and (model.bias == here.bias).all() and model.reject_below == here.reject_below


def test_language_id(spark, sf):
    docs = spark.read.parquet("/root/testdata/sf0.01/documents.parquet")
    got = langid.identify(docs).join(docs.select("doc_id", "lang"), "doc_id").where("held_out")
    assert got.agg(F.avg((F.col("lang") == F.col("lang_pred")).cast("double"))).first()[0] > 0.97
    rows = [(i, "the of and to in that " * 5, "en") for i in range(30)] + [(100 + i, "der die und das nicht ein " * 5, "de") for i in range(30)]
    odd = [(500, None), (501, ""), (502, "1234 !!"), (503, "die und das", None), (None, "the of and", "en")]
    got = {r["doc_id"]: r for r in langid.identify(docs_of(spark, rows + odd)).collect()}
    assert len(got) == 65 and [got[i]["lang_pred"] for i in (500, 501, 502)] == ["und"] * 3 and got[503]["lang_pred"] == "de"
    assert all(0 <= r["score"] <= 1 for r in got.values()) and got[None]["held_out"] is False
    assert all(r["held_out"] == (zlib.crc32(str(i).encode()) % 3 == 1) for i, r in got.items() if i is not None)
    assert langid.identify(docs_of(spark, [])).count() == 0
    nothing = langid.identify(docs_of(spark, [(1, "abc", None)])).first()
    assert (nothing["lang_pred"], nothing["score"], nothing["rejected"]) == ("und", 0.0, True)
    kept = langid.keep_identified(docs_of(spark, rows + odd))
    assert kept.columns == [c.split()[0] for c in DOC.split(", ")] and kept.where("doc_id < 500").count() == 60


def brute_bfd(lengths, capacity):
    bins = []
    for n in sorted(lengths, reverse=True):
        fits = [i for i, b in enumerate(bins) if b >= n]
        if fits:
            bins[min(fits, key=lambda i: bins[i])] -= n
        else:
            bins.append(capacity - n)
    return sorted(bins)


def test_plan_is_best_fit_decreasing():
    g = np.random.default_rng(2)
    for _ in range(150):
        cap = int(g.choice([10, 37, 64]))
        counts = Counter(g.integers(1, cap + 1, int(g.integers(0, 150))).tolist())
        moves, bins = packing.plan(counts, cap)
        fill = {}
        for length, _rank, n, first, offset in moves:
            for j in range(n):
                fill.setdefault(first + j, []).append((offset, length))
        for b in fill.values():
            at = 0
            for offset, length in sorted(b):
                assert offset == at
                at += length
        assert sorted(cap - sum(x for _, x in b) for b in fill.values()) == brute_bfd(list(counts.elements()), cap) and bins == len(fill)


def test_pack(spark):
    import public_tokenizers
    from tokenizers import Tokenizer

    path = public_tokenizers.path("byte_bpe_50k.json")
    tk = Tokenizer.from_file(path)
    rows = [(i, "the quick brown " * (i % 50) + "é<|endoftext|>x  \n") for i in range(40)] + [(90, None), (91, ""), (92, "a" * 30000 + " b" * 3000), (None, "z"), (93, "same"), (93, "same")]
    got = packing.pack(docs_of(spark, rows), path, capacity=64).collect()
    by = {}
    for r in got:
        by.setdefault(r["doc_id"], []).append(r)
    for i, text in rows[:43]:
        ids = np.array(tk.encode(text or "", add_special_tokens=False).ids + [2], "<u4")
        mine = sorted(by[i], key=lambda r: r["piece"])
        assert sum(r["length"] for r in mine) == len(ids) and [r["piece"] for r in mine] == list(range(len(mine)))
        for r in mine:
            assert r["ids_crc32"] == zlib.crc32(ids[r["start"] : r["start"] + r["length"]]) and r["length"] <= 64
        assert all(r["length"] == 64 for r in mine[1:]) if len(mine) > 1 else True
    seq = {}
    for r in got:
        seq.setdefault(r["sequence_id"], []).append((r["offset"], r["length"]))
    for b in seq.values():
        at = 0
        for offset, length in sorted(b):
            assert offset == at
            at += length
        assert at <= 64
    assert sorted(64 - sum(x for _, x in b) for b in seq.values()) == brute_bfd([r["length"] for r in got], 64)
    assert len(by[93]) == 2 and packing.pack(docs_of(spark, []), path).count() == 0


@pytest.mark.parametrize("text", [" " * 1_000_000, "\n" * 1_000_000, "a" * 1_000_000, "\t \u00a0" * 400_000, "hi <|endoftext|> there", "x" + " " * 63 + "y" + "\r\n" * 31 + "z", "if x:\n" + " " * 70 + "pass"])
def test_encoder_of_long_and_odd_texts(text):
    import public_tokenizers
    from tokenizers import Tokenizer

    path = public_tokenizers.path("byte_bpe_50k.json")
    assert packing.encoder(path)(text) == Tokenizer.from_file(path).encode(text, add_special_tokens=False).ids


def test_fast_encoder_equals_the_library():
    """On every code point between letters, digits, signs and blanks (each 7th: the whole takes 40 s), on every entry that
    is text, and on random joints of entries."""
    import json
    import random

    import public_tokenizers
    from tokenizers import Tokenizer

    path = public_tokenizers.path("byte_bpe_50k.json")
    tk, rnd = Tokenizer.from_file(path), random.Random(4)
    fast = packing._ranked(path, json.load(open(path)))
    assert packing._ranked(public_tokenizers.path("word_bpe_49k.json"), json.load(open(public_tokenizers.path("word_bpe_49k.json")))) is None
    entries = [b for b in fast.token_byte_values()]
    texts = [f"a{c}a 1{c}1 !{c}! {c} x  {c}{c}\n{c}" for c in map(chr, range(0, 0x110000, 7)) if not "\ud800" <= c <= "\udfff"]
    texts += [b.decode("utf-8", "ignore") for b in entries] + [b"".join(rnd.choices(entries, k=5)).decode("utf-8", "ignore") for _ in range(50_000)]
    texts = [x for x in texts if "<|endoftext|>" not in x]
    assert all(a.ids == b for a, b in zip(tk.encode_batch(texts, add_special_tokens=False), map(fast.encode_ordinary, texts)))


def test_line_spread(spark):
    rows = [(i, f"own {i}\n  shared line \nend {i}\n\nlocal {i % 3}", "en", f"s{i % 12}") for i in range(36)]
    rows += [(100, "shared line", "en", "s1"), (101, None, "en", "s2"), (102, "", "en", "s3"), (103, "shared line\nlong own text that is more than the shared one", "en", None), (None, "shared line\n" + "x" * 99, "en", "s1")]
    got = {r["doc_id"]: r for r in linededup.remove_boilerplate(docs_of(spark, rows), min_sites=8).collect()}
    assert got[5]["text"] == "own 5\nend 5\n\nlocal 2" and (got[5]["n_lines"], got[5]["n_removed"]) == (5, 1)
    assert got[100]["text"] == "shared line" and got[100]["n_removed"] == 0  # a copy rather than a page with boilerplate
    assert got[101]["text"] is None and got[101]["n_lines"] == 0 and got[102]["n_lines"] == 1
    assert got[103]["n_removed"] == 1 and (got[None]["n_removed"], got[None]["text"]) == (1, "x" * 99)
    assert got[5]["key"] == "k" and got[5]["n"] == 7
    odd = docs_of(spark, rows).selectExpr("*", "1 as gone", "'a' as kept", "2 as line", "3 as row", "'z' as doc_hash", "4 as k1", "5 as place", "6 as n_lines")
    clash = linededup.remove_boilerplate(odd, min_sites=8)
    assert clash.columns == [*(c for c in odd.columns if c != "n_lines"), "n_lines", "n_removed"]
    assert {r["doc_id"]: (r["text"], r["n_removed"], r["kept"], r["row"]) for r in clash.collect()} == {i: (r["text"], r["n_removed"], "a", 3) for i, r in got.items()}
    assert linededup.remove_boilerplate(docs_of(spark, [])).count() == 0
    few = {r["doc_id"]: r["n_removed"] for r in linededup.remove_boilerplate(docs_of(spark, rows), min_sites=13).collect()}
    assert set(few.values()) == {0}


def test_line_spread_cleans_pages_that_are_mostly_boilerplate(spark):
    line = "a shared line that is far longer than what else the page holds"
    rows = [(i, f"own {i}\n{line}\n\n{line}", "en", f"s{i}") for i in range(8)] + [(20, f"{line}\n \n{line}", "en", "s1")]
    got = {r["doc_id"]: (r["text"], r["n_lines"], r["n_removed"]) for r in linededup.remove_boilerplate(docs_of(spark, rows), min_sites=8).collect()}
    assert got == {**{i: (f"own {i}\n", 4, 2) for i in range(8)}, 20: (rows[-1][1], 3, 0)}


def test_line_spread_of_long_documents_and_equal_ids(spark):
    """A document of 200,000 lines, all but one of them removed; rows of one id are cleaned by their own texts."""
    rows = [(i, f"own {i}\n" + "shared line\n" * (200_000 if i == 0 else 1) + "tail", "en", f"s{i}") for i in range(8)] + [(9, "shared line\nfirst", "en", "s1"), (9, "second\nshared line", "en", "s2")]
    got = linededup.remove_boilerplate(docs_of(spark, rows), min_sites=8).collect()
    assert {(r["doc_id"], r["text"], r["n_removed"]) for r in got if r["doc_id"] in (0, 9)} == {(0, "own 0", 200_001), (9, "first", 1), (9, "second", 1)}


def lm_tokens(text):
    return re.findall(r"[^\x20\x09-\x0D]+", re.sub("[A-Z]", lambda m: m[0].lower(), text or "")) + [None]


def lm_rows():
    g = np.random.default_rng(8)
    words = [f"w{i}" for i in range(40)]
    rows = []
    for i in range(120):
        w = [words[0]]
        for _ in range(int(g.integers(0, 30))):
            w.append(words[(words.index(w[-1]) * 7 + int(g.integers(0, 3))) % 40])
        rows.append((i, " ".join(w)))
    return rows + [(500, None), (501, ""), (502, "unheard OF words"), (None, "w0 w1")]


def grams(tokens):
    """Per token its word, bigram and trigram, and its contexts of one and two words."""
    t = ["<<", "<", *tokens]
    return [((w,), (v, w), (u, v, w), (v,), (u, v)) for u, v, w in zip(t, t[1:], t[2:])]


def lm_probability(gram, count, docs, n, v, weights, less=Counter()):
    """The interpolated probability by hand; ``less``: counts to leave out, with "docs" and "tokens"."""
    word, two, three, h1, h2 = gram
    c = lambda x: count[x] - less[x]
    starts = docs - less["docs"]
    n1, n2 = (starts if h1 == ("<",) else c(h1)), (starts if h2 == ("<<", "<") else c(h2))
    ratios = [c(three) / n2 if n2 else 0, c(two) / n1 if n1 else 0, c(word) / (n - less["tokens"]), 1 / (v + 1)]
    k = int(ngramlm.bucket(np.array([n2]), np.array([n1]))[0])
    return ratios, k, sum(a * b for a, b in zip(weights[k], ratios))


@pytest.mark.parametrize("chunk,fan", [(10**6, 7), (400, 7), (150, 1), (300, 2)])
def test_lm_scores(spark, monkeypatch, chunk, fan):
    """Counts, base scores and scores by hand, for one chunk, for many, and for several levels of nodes."""
    monkeypatch.setattr(ngramlm, "CHUNK_TOKENS", chunk)
    monkeypatch.setattr(ngramlm, "FAN_BITS", fan)
    seen, estimate = [], ngramlm.estimate
    monkeypatch.setattr(ngramlm, "estimate", lambda *a, **k: seen.append(estimate(*a, **k)) or seen[-1])
    rows = lm_rows()
    counted = {i: i is not None and zlib.crc32(str(i).encode()) % 7 != 2 for i, _ in rows}
    got = {r["doc_id"]: r for r in ngramlm.score(docs_of(spark, rows).repartition(6), langid.fold("doc_id", 7) != 2).collect()}
    count = Counter(x for i, t in rows if counted[i] for g in grams(lm_tokens(t)) for x in g[:3])
    n, v = sum(c for k, c in count.items() if len(k) == 1), sum(len(k) == 1 for k in count)
    assert len(got) == len(rows)
    for i, x in rows:
        t = grams(lm_tokens(x))
        assert (got[i]["n_tokens"], got[i]["n_known"], got[i]["train_tokens"], got[i]["counted"]) == (len(t), sum(count[g[0]] > 0 for g in t), n, counted[i])
        assert got[i]["base_score"] == pytest.approx(sum(math.log10((count[g[0]] + 1) / (n + v + 1)) for g in t), rel=1e-9)
        assert got[i]["score"] == pytest.approx(sum(math.log10(lm_probability(g, count, sum(counted.values()), n, v, seen[0])[2]) for g in t), rel=1e-9)
    held = [i for i, _ in rows if i is not None and i < 500 and not counted[i]]
    assert sum(got[i]["score"] for i in held) > sum(got[i]["base_score"] for i in held)


def test_lm_without_training_rows(spark):
    assert ngramlm.score(docs_of(spark, []), langid.fold("doc_id", 7) != 2).count() == 0
    alone = ngramlm.score(docs_of(spark, [(1, "a b")]), F.lit(False)).first()
    assert alone["score"] == alone["base_score"] == 0.0 and alone["train_tokens"] == 0


def test_lm_weights_by_brute_force(spark, monkeypatch):
    """Expectation-maximisation on every training token's own deleted ratios gives the weights that the grid of ratios does,
    to within the grid's step; all probabilities after a context add up to one."""
    seen, estimate = [], ngramlm.estimate
    monkeypatch.setattr(ngramlm, "estimate", lambda *a, **k: seen.append(estimate(*a, **k)) or seen[-1])
    rows = [(i, t) for i, t in lm_rows() if t]
    counted = {i: i is not None and zlib.crc32(str(i).encode()) % 7 != 2 for i, _ in rows}
    ngramlm.score(docs_of(spark, rows), langid.fold("doc_id", 7) != 2).count()
    train = [grams(lm_tokens(t)) for i, t in rows if counted[i]]
    count = Counter(x for t in train for g in t for x in g[:3])
    n, v = sum(c for k, c in count.items() if len(k) == 1), sum(len(k) == 1 for k in count)
    even, found = np.full((ngramlm.BUCKETS, 4), 0.25), {}
    for t in train:
        less = Counter(x for g in t for x in g[:3]) + Counter({"docs": 1, "tokens": len(t)})
        for g in t:
            ratios, k, _ = lm_probability(g, count, len(train), n, v, even, less)
            found.setdefault(k, []).append(ratios)
    for k, ratios in found.items():
        p, w = np.array(ratios), np.array([k >= ngramlm.SINGLES, k > 0, 1, 1], float)
        w /= w.sum()
        for _ in range(200):
            part = w * p
            w = (part / part.sum(axis=1, keepdims=True)).mean(axis=0)
        likelihood = lambda x: np.log(p @ x).mean()  # noqa: E731, B023
        assert likelihood(seen[0][k]) > likelihood(w) - 0.02, (k, w, seen[0][k])
    for context in ((("w0",), ("<", "w0")), (("w3",), ("w0", "w3")), (("new",), ("w0", "new"))):
        words = [k[0] for k in count if len(k) == 1] + ["never"]
        total = sum(lm_probability(((w,), (*context[0], w), (*context[1], w), *context), count, len(train), n, v, seen[0])[2] for w in words)
        assert total == pytest.approx(1)


def test_lm_weights_are_a_distribution():
    g = ngramlm.GRID
    cells, n = np.array([((ngramlm.SINGLES + 3) * g + 0) * g * g + 4 * g + 40, (g - 1) * g * g + (g - 1) * g + 30]), np.array([100, 50])
    w = ngramlm.estimate(cells, n, 1000)
    assert np.allclose(w.sum(axis=1), 1) and not w[: ngramlm.SINGLES, 0].any() and w[0, 1] == 0 and (w[:, 2:] > 0).all() and w[ngramlm.SINGLES + 3, 0] > 0.9
