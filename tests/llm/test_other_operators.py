"""Embedding groups, archives, shard compaction, image copies and the pipeline."""

import gzip

import numpy as np
import pytest

import corpus_pipeline
from apcube.llm import compaction, imagematch, itq, thumbnails, warc
from apcube.llm.storage import new_path


def vectors():
    g = np.random.default_rng(4)
    base = g.normal(size=(40, 16))
    rows = [(i, x.tolist(), i % 3) for i, x in enumerate(base)]
    rows += [(100 + i, (base[1] + 0.04 * g.normal(size=16)).tolist(), 1) for i in range(70)]
    rows += [(300 + i, base[2].tolist(), 2) for i in range(30)] + [(400, base[2].tolist(), 1), (401, (-base[2]).tolist(), 2)]
    rows += [(600 + i, (np.tile(base[3], 2)[:24] + 0.03 * g.normal(size=24)).tolist(), i % 2) for i in range(20)]  # a lesser width
    return rows + [(500, None, 1), (501, [], 1), (502, [0.0] * 16, 1), (503, [float("nan")] * 16, 1), (504, base[1].tolist(), None), (505, [1.0, 2.0], 1), (506, [None] * 16, 1), (507, [float("inf")] * 16, 1)]


@pytest.mark.parametrize("block", [16, 2048])
def test_itq_equals_brute_force(spark, monkeypatch, block):
    monkeypatch.setattr(itq, "BLOCK", block)
    rows = vectors()
    df = spark.createDataFrame(rows, "vec_id bigint, embedding array<float>, label int").selectExpr("*", "1 as rep", "'x' as key")
    got = {r["vec_id"]: (r["n_links"], r["component_id"], r["kept"]) for r in itq.near_duplicates(df, rotations=8, substring=8).collect()}
    good = {i: (np.array(v, np.float32).astype(float), lb) for i, v, lb in rows if v and lb is not None and None not in v and np.isfinite(v).all() and any(v)}
    links = {i: {j for j, (y, m) in good.items() if j != i and m == lb and len(x) == len(y) and x @ y / np.sqrt((x @ x) * (y @ y)) >= 0.98} for i, (x, lb) in good.items()}
    assert len(got) == len(rows)
    for i, _, _ in rows:
        reach, todo = {i}, [i]
        while todo:
            new = links.get(todo.pop(), set()) - reach
            reach |= new
            todo += new
        assert got[i] == (len(links.get(i, ())), min(reach), min(reach) == i)


def test_itq_recall_at_the_registered_parameters(spark):
    """Near copies of 64 components whose cosines spread from 0.98 to 1, among unrelated vectors: links found of all links."""
    g = np.random.default_rng(9)
    unit = lambda x: x / np.sqrt((x * x).sum(axis=1))[:, None]
    base = unit(g.normal(size=(2500, 64)))
    of, cosine = g.integers(0, 400, 1200), g.uniform(0.975, 1, 1200)
    away = g.normal(size=(1200, 64))
    away = unit(away - (away * base[of]).sum(axis=1)[:, None] * base[of])
    x = np.concatenate([base, base[of] * cosine[:, None] + away * np.sqrt(1 - cosine**2)[:, None]])
    df = spark.createDataFrame([(i, v.tolist(), 1) for i, v in enumerate(x)], "vec_id bigint, embedding array<double>, label int")
    got = np.zeros(len(x), int)
    for r in itq.near_duplicates(df).collect():
        got[r["vec_id"]] = r["n_links"]
    c = x @ x.T
    want = ((c / np.sqrt(np.outer(c.diagonal(), c.diagonal())) >= 0.98).sum(axis=1)) - 1
    assert want.sum() > 1500 and (got <= want).all()
    print("recall", got.sum() / want.sum())
    assert got.sum() >= 0.99 * want.sum()


def test_itq_without_rows(spark):
    none = spark.createDataFrame([], "vec_id bigint, embedding array<float>, label int")
    assert itq.near_duplicates(none).count() == 0
    odd = spark.createDataFrame([(1, None, 1), (None, [1.0], 1)], "vec_id bigint, embedding array<float>, label int")
    assert sorted((r["n_links"], r["kept"]) for r in itq.near_duplicates(odd).collect()) == [(0, True), (0, True)]


PAGES = [(3, "http://a.b/ü x", "<p>é</p>"), (1, None, "<p>é</p>"), (2, "http://c", None), (9, "http://d", ""), (None, "u", "<p>é</p>"), (7, "http://e\r\nX: y", "z" * 50000), (8, "w", "one"), (8, "w", "one")]


def test_warc_round_trip(spark):
    df = spark.createDataFrame(PAGES + [(100 + i, f"http://h/{i}", f"page {i} " * 500) for i in range(60)], "page_id bigint, url string, html string").selectExpr("*", "1 as k", "'y' as digest")
    out, again = new_path(spark, "warc"), new_path(spark, "warc")
    warc.write(df, out, shard_bytes=100_000, file_bytes=2_000)
    rows = warc.read(spark, out).collect()
    assert len(rows) == 68
    by = {r["page_id"]: r for r in rows}
    assert (by["1"]["record_type"], by["3"]["record_type"], by["3"]["refers_to"], by[None]["refers_to"]) == ("response", "revisit", "1", "1")
    assert (by["2"]["record_type"], by["9"]["refers_to"], by["9"]["payload_bytes"]) == ("response", "2", 0)
    assert [r["record_type"] for r in rows if r["page_id"] == "8"] == ["response", "response"]
    assert by["3"]["payload_bytes"] == len("<p>é</p>".encode()) and by["3"]["payload"] is None and by["1"]["payload"] == "<p>é</p>".encode()
    assert by["3"]["payload_digest"] == by["1"]["payload_digest"] == warc._digest("<p>é</p>".encode())
    warc.write(df.repartition(5), again, shard_bytes=100_000, file_bytes=2_000)
    name = lambda p: {(r["name"], r["sha256"], r["records"]) for r in warc.manifest(spark, p).collect()}
    assert name(out) == name(again) and len(name(out)) > 3
    with pytest.raises(Exception):  # noqa: B017
        warc.write(df, out)
    assert warc.clean(spark, out) == 0
    path = f"{out.removeprefix('file://')}/{warc.manifest(spark, out).orderBy('name').first()['path']}"
    assert gzip.open(path).read().startswith(b"WARC/1.1\r\nWARC-Type: warcinfo\r\n")
    large = new_path(spark, "warc")
    warc.write(df, large, min_payload=10)
    got = {r["page_id"]: r["record_type"] for r in warc.read(spark, large).collect()}
    assert got["9"] == got["3"] == "response"


def test_warc_without_rows_and_damage(spark):
    out = new_path(spark, "warc")
    assert warc.write(spark.createDataFrame([], "page_id bigint, url string, html string"), out).count() == 0
    assert warc.read(spark, out).count() == 0
    raw = warc._page("1", "u", b"abc", None, "2000-01-01T00:00:00Z")
    assert warc.parse(raw)[0]["warc-type"] == "response"
    with pytest.raises(ValueError):
        warc.parse(raw.replace(b"abc", b"abd"))


def test_warc_writers_that_die_or_meet(spark, monkeypatch):
    df = spark.createDataFrame(PAGES, "page_id bigint, url string, html string")
    out, real = new_path(spark, "warc"), warc.publish
    expected = None
    for step in ("materialize", "publish"):  # a writer dies before its files are moved, and before it commits
        with monkeypatch.context() as m:
            keep = getattr(warc, step)
            m.setattr(warc, step, lambda *a, **k: (_ for _ in ()).throw(OSError("lost")) if step == "publish" or a[1] == "staged" else keep(*a, **k))  # noqa: B023
            with pytest.raises(OSError):
                warc.write(df, out)
        with pytest.raises(Exception):  # noqa: B017
            warc.read(spark, out)

    def late(*a):  # another writer commits while this one is about to
        monkeypatch.setattr(warc, "publish", real)
        warc.write(df.where("page_id = 7"), out)
        return real(*a)

    monkeypatch.setattr(warc, "publish", late)
    with pytest.raises(FileExistsError):
        warc.write(df, out)
    rows = warc.read(spark, out).collect()
    assert [r["page_id"] for r in rows] == ["7"] and warc.clean(spark, out) == 2 and warc.read(spark, out).count() == 1
    path = f"{out.removeprefix('file://')}/{warc.manifest(spark, out).first()['path']}"
    raw = open(path, "rb").read()
    extra = warc._member(warc._page("8", "u", b"new", None, "2000-01-01T00:00:00Z"), 6)
    open(path, "wb").write(raw + extra)  # whole records, but not those of the manifest
    with pytest.raises(Exception, match="not the file that was committed"):
        warc.read(spark, out).count()
    assert expected is None


def test_warc_cuts(spark):
    """Runs of ids hold at most a shard, though one id is far away, ids are dense, or all are negative."""
    for ids in ([*range(1000), 1 << 62], [-(1 << 62), *range(5_000_000, 5_000_500)], [7], [-5, -4, 3, (1 << 63) - 1, -(1 << 63)]):
        rows = spark.createDataFrame([(i, 10) for i in ids] + [(None, 5)], "k bigint, n bigint")
        cuts = warc.cuts_of(rows, "k", "n", 70)
        n = np.bincount(np.searchsorted(cuts, np.array(ids), side="right"), minlength=len(cuts) + 1)
        assert n.max() <= 7 and (n[:-1] + n[1:] > 3).all() and (np.diff(cuts) > 0).all()
    assert len(warc.cuts_of(spark.createDataFrame([(3, 99), (3, 99), (4, 1)], "k bigint, n bigint"), "k", "n", 70)) == 1


def test_compaction_writers_that_die_or_meet(spark, monkeypatch):
    import json
    import os

    df = spark.createDataFrame([(i, "x" * i) for i in range(30)], "doc_id bigint, __arrival string")
    store = compaction.ShardStore(spark, new_path(spark, "store"), target_bytes=1 << 20, fan_in=2)
    store.append(df.limit(10))
    folder = f"{store.root.removeprefix('file://')}/_versions"
    with monkeypatch.context() as m:  # dies with all files written and nothing committed
        m.setattr(compaction, "publish", lambda *a: (_ for _ in ()).throw(OSError("lost")))
        with pytest.raises(OSError):
            store.append(df)
    assert store.read().count() == 10 and store.versions() == [1]
    open(f"{folder}/0000000002.json", "w").close()  # what a writer without atomic commits would leave
    open(f"{folder}/0000000003.json", "w").write(json.dumps({"version": 3})[:5])
    assert store.append(df.where("doc_id >= 10")) == 4 and store.read().count() == 30 and store.versions() == [1, 4]
    real, turns = compaction.publish, []

    def late(*a):  # another writer's append comes first
        if not turns:
            turns.append(1)
            store.append(df.limit(1))
        return real(*a)

    monkeypatch.setattr(compaction, "publish", late)
    assert store.append(df.limit(2)) == 6 and store.read().count() == 33
    turns.clear()
    assert store.compact()[0] == 8 and store.read().count() == 34  # the merge was made anew upon the append
    assert [f for f in os.listdir(folder) if f.endswith(".tmp")] == []
    assert store.append_batches(df, df.doc_id % 2) == [9, 10] and store.read().where("__arrival = 'x'").count() >= 2


def test_publish_by_renaming(spark):
    from apcube.llm import storage

    path = new_path(spark, "published")
    system, source = storage.hadoop(spark, f"{path}/a")
    system.create(source).close()
    target = storage.hadoop(spark, f"{path}/b")[1]
    storage._rename_new(spark, source, target)
    system.create(source).close()
    with pytest.raises(Exception, match="AlreadyExists|already exists"):
        storage._rename_new(spark, source, target)


def test_compaction(spark):
    rows = [(i, "x" * (i % 700) if i % 9 else None, i % 4) for i in range(3000)] + [(None, "", None), (5, "dup", 1), (5, "dup", 1)]
    df = spark.createDataFrame(rows, "doc_id bigint, text string, path int")
    store = compaction.ShardStore(spark, new_path(spark, "store"), target_bytes=200_000, fan_in=3)
    versions = store.append_batches(df, df.doc_id % 6)
    assert versions == list(range(1, len(versions) + 1))
    before = store.manifest().count()
    done = store.compact()
    assert done and store.manifest().count() < before
    assert sorted(map(str, store.read().collect())) == sorted(map(str, df.collect()))
    assert store.read(versions[0]).count() < len(rows)  # older versions stay readable until vacuumed
    assert store.vacuum() > 0 and store.read().count() == len(rows) and store.compact() == []
    assert store.append(df.limit(10)) == done[-1] + 1 and store.read().count() == len(rows) + 10
    with pytest.raises(compaction.CommitConflict):
        store._commit(1, store.manifest().select("path", "bytes", "rows"), df.schema, "late")
    empty = compaction.compacted(df.where("doc_id < -1"), new_path(spark, "store"))
    assert empty.read().count() == 0 and empty.read().columns == df.columns


def test_image_copies(spark):
    pages = spark.createDataFrame([(i, " ".join(f"w{(i * 131 + j * 7) % 9973}" for j in range(80)) if i % 37 else None) for i in range(240)], "page_id bigint, html string")
    images = thumbnails.thumbnails(pages).selectExpr("*", "1 as key", "2 as p")
    asked = thumbnails.edited(thumbnails.thumbnails(pages.where("page_id % 20 = 0")))
    odd = spark.createDataFrame([(9000, None, 64, 64), (9001, bytearray(b"ab"), 64, 64), (None, bytearray(4096), 64, 64), (9002, bytearray(25), 5, 5), (9003, bytearray(4096), 64, 64)], "id bigint, pixels binary, height int, width int").selectExpr("*", "1 as key", "2 as p")
    twins = images.where("id = 20").selectExpr("9500 as id", "pixels", "height", "width", "1 as key", "2 as p")
    got = imagematch.search(images.union(odd).union(twins), asked).collect()
    hit = {r["query_id"] for r in got if r["query_id"] == r["image_id"]}
    assert len(hit) >= 9 and sum(r["query_id"] != r["image_id"] for r in got) <= 1
    assert [r["copies"] for r in got if (r["query_id"], r["image_id"]) == (20, 20)] == [2]
    turned = [r["turn"] for r in got if r["query_id"] == r["image_id"] == 40]
    assert turned and abs(abs(turned[0]) - np.pi / 2) < 0.2
    assert imagematch.search(images.limit(0), asked.limit(0)).count() == 0


def _drawn(spark, n):
    pages = spark.createDataFrame([(i, " ".join(f"w{(i // 2 * 131 + j * 7 + (j == 40) * i) % 9973}" for j in range(80))) for i in range(n)], "page_id bigint, html string")
    return thumbnails.thumbnails(pages), thumbnails.edited(thumbnails.thumbnails(pages.where("page_id % 20 = 0")))


def test_image_copies_by_the_tables_in_groups(spark, monkeypatch):
    """Pairs looked at are those that meet twice, or once in near corners; groups and slices of any size give all of them."""
    images, asked = _drawn(spark, 120)
    found = sorted(map(tuple, imagematch.search(images, asked).collect()))
    points = lambda df, scales: {r["id"]: np.frombuffer(r["points"], imagematch.POINT) for r in imagematch.describe(df, scales).collect()}
    want, looked, described = [], 0, points(images, imagematch.SCALES)
    for q, a in points(asked, imagematch.QUERY_SCALES).items():
        for i, b in described.items():
            equal = sum((a["bits"][:, None, k : k + 5] == b["bits"][None, :, k : k + 5]).all(axis=2).astype(int) for k in range(0, 30, 5))
            near = np.bitwise_count(a["bits"][:, None] ^ b["bits"][None]).sum(axis=2, dtype=int) <= imagematch.MOST_BITS_OFF
            if equal.sum() > 1 or (near & (equal > 0)).any():
                looked += 1
                m = imagematch.matches(a, b)
                votes, at = imagematch.consensus(m) if len(m) >= 5 else (0, 0)
                if votes >= 5:
                    want.append((q, i, votes, 1, float(m[at, 4]), float(m[at, 5])))
    assert found == sorted(want) and looked > len(want) >= 10
    described = imagematch.describe(asked, imagematch.QUERY_SCALES).select("id", "points")
    described.coalesce(1).write.parquet(path := new_path(spark, "asked"))
    rows = images.toArrow().to_batches()
    for group, part, cells in (((1, 9), (1, 9), 2), ((300, 9), (1 << 18, 3), 700), ((1 << 19, 50), (2000, 9), 1 << 20)):
        for name, v in (("GROUP", group), ("SLICE", part), ("CELLS", cells)):
            monkeypatch.setattr(imagematch, name, v)
        some = [r for b in imagematch._matcher(sorted(spark.read.parquet(path).inputFiles()), [], 5, False)(iter(rows)) for r in b.to_pylist()]
        assert sorted((r["query_id"], r["image_id"], r["inliers"], 1, r["turn"], r["zoom"]) for r in some) == found


def test_image_copies_write_no_corners_of_images(spark):
    """What is written is the queries' corners and a few numbers an image, not the corners of the images or their keys."""
    from pathlib import Path

    from apcube.llm.storage import shared_dir

    shared = Path(shared_dir(spark).removeprefix("file:"))
    size = lambda: sum(p.stat().st_size for p in shared.rglob("*.parquet"))
    images, asked = _drawn(spark, 1200)
    corners = imagematch.describe(images, imagematch.SCALES).selectExpr("sum(octet_length(points)) as n").first()["n"]
    before = size()
    assert imagematch.search(images, asked.where("id % 60 = 0")).count() > 0
    assert 0 < size() - before < corners / 4


def test_pipeline_stages(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    n = docs.count()
    for name, stage in corpus_pipeline.STAGES[:-1]:
        out = stage(spark, docs, sf).cache()
        assert out.columns == docs.columns and out.count() > 0, name
        if name != "mixing":
            assert out.count() <= docs.count() and out.select("doc_id").distinct().count() == out.count()
        docs = out
    assert docs.select("doc_id").distinct().count() <= n
    packed = corpus_pipeline.STAGES[-1][1](spark, docs, sf)
    assert packed.select("doc_id").distinct().count() == docs.select("doc_id").distinct().count()
    assert corpus_pipeline.run(spark, sf).agg({"length": "sum"}).first() == packed.agg({"length": "sum"}).first()


def test_pipeline_handles_awkward_documents(spark, sf):
    rows = [(1, None, None, None, None), (2, "", "en", "a", 0), (None, "the of and to", "en", None, 5), (3, "the of and to " * 9, "en", "a", 9), (3, "the of and to " * 9, "en", "a", 9)]
    docs = spark.createDataFrame(rows, "doc_id bigint, text string, lang string, source string, n_chars bigint")
    for frame in (docs, docs.limit(0)):
        for _name, stage in corpus_pipeline.STAGES:
            frame = stage(spark, frame, sf).cache()
            frame.count()


def test_image_copies_of_every_kind(spark):
    """Recall by kind of edit; an image's corners aren't capped, and queries meet images between the images' scales."""
    g = np.random.default_rng(0)
    weight = g.normal(size=(40, thumbnails.PATTERNS))
    weight /= np.sqrt((weight**2).sum(axis=1))[:, None]
    pictures = np.clip(128 + 45 * weight @ thumbnails._patterns(), 0, 255).reshape(-1, thumbnails.SIDE, thumbnails.SIDE)
    sized = lambda p, n: imagematch.resize(p[None].astype(np.float32), n, n)[0]
    kinds = {"crop": lambda p, i: thumbnails.edit(p, "crop", i), "deep crop": lambda p, i: p[i % 20 : i % 20 + 44, 7:51], "0.6": lambda p, i: sized(p, 38), "0.85": lambda p, i: sized(p, 54)}
    kind = "id bigint, pixels binary, height int, width int"
    row = lambda i, p: (i, bytearray(np.round(p).astype(np.uint8).tobytes()), *p.shape)
    images = spark.createDataFrame([row(i, p) for i, p in enumerate(pictures)], kind)
    asked = spark.createDataFrame([row(1000 * k + i, f(p, i)) for k, f in enumerate(kinds.values()) for i, p in enumerate(pictures)], kind)
    got = [(r["query_id"], r["image_id"]) for r in imagematch.search(images, asked).collect()]
    assert all(q % 1000 == i for q, i in got)
    for k, name in enumerate(kinds):
        assert sum(q // 1000 == k for q, _ in got) >= 0.9 * len(pictures), name


def test_image_copies_leave_out_no_pair(spark):
    """The query's pairs are those of a test of every corner of every query with every corner of every image."""
    from apcube.llm.queries import op4_image_copies

    pages = spark.read.parquet("/root/testdata/sf0.01/pages.parquet")
    images, asked = thumbnails.thumbnails(pages), thumbnails.edited(thumbnails.thumbnails(pages.where("page_id % 20 = 0")))
    points = lambda df, scales: {r["id"]: np.frombuffer(r["points"], imagematch.POINT) for r in imagematch.describe(df, scales).collect()}
    want, described = {}, points(images, imagematch.SCALES)
    for q, a in points(asked, imagematch.QUERY_SCALES).items():
        for i, b in described.items():
            m = imagematch.matches(a, b)
            if len(m) >= 5 and imagematch.consensus(m)[0] >= 5:
                want[q, i] = imagematch.consensus(m)[0]
    got = {(r["query_id"], r["image_id"]): r["inliers"] for r in op4_image_copies(spark, "/root/testdata/sf0.01").collect()}
    assert got == want and len(want) > len(asked.collect())


def test_image_copies_of_any_number_of_pairs(spark, monkeypatch):
    """No number of pairs makes the query leave out some (beyond 2^19 it once took those of the tables alone)."""
    from apcube.llm.queries import op4_image_copies

    pages = spark.read.parquet("/root/testdata/sf0.01/pages.parquet")
    images, asked = thumbnails.thumbnails(pages), thumbnails.edited(thumbnails.thumbnails(pages.where("page_id % 20 = 0")))
    every, met = (sorted(map(tuple, imagematch.search(images, asked, exact=exact).collect())) for exact in (True, False))
    monkeypatch.setattr(imagematch, "MOST_PAIRS", 1, raising=False)
    assert sorted(map(tuple, op4_image_copies(spark, "/root/testdata/sf0.01").collect())) == every and len(every) > len(met)
