"""Groups of near copies against brute force."""

import random

import edgeconn.llm.nearcopies as N


def brute(rows, similarity=0.8):
    """Least id of each id's group: all pairs, sets of whole shingles."""
    sets = {}
    for i, t in rows:
        w = (t or "").encode().lower().split()
        sets[i] = {tuple(w[j : j + 5]) for j in range(len(w) - 4)} or ({tuple(w)} if w else set())
    near = lambda a, b: a == b or (a and b and len(a & b) / (len(a) * len(b)) ** 0.5 >= similarity)
    comp = {}
    for i in sorted(sets):
        if i in comp:
            continue
        comp[i], front = i, [i]
        while front:
            x = front.pop()
            for j in sorted(sets):
                if j not in comp and near(sets[x], sets[j]):
                    comp[j] = i
                    front.append(j)
    return comp


def kept_of(spark, rows):
    return {r.doc_id for r in N.one_of_each(spark.createDataFrame(rows, "doc_id long, text string")).collect()}


def test_given_documents(spark, small):
    docs = spark.read.parquet(f"{small}/documents.parquet")
    rows = [(r.doc_id, r.text) for r in docs.collect()]
    out = N.one_of_each(docs)
    assert out.columns == docs.columns
    assert {r.doc_id for r in out.collect()} == set(brute(rows).values())


def test_scattered_and_block_edits_and_common_passages(spark):
    rng = random.Random(3)
    words = [f"w{i}" for i in range(3000)]
    passage = [rng.choice(words) for _ in range(60)]
    rows = []
    for g in range(40):
        t = [rng.choice(words) for _ in range(260)] + passage  # a passage that all share brings none together
        rows.append((10 * g, " ".join(t)))
        scattered = list(t)
        for at in rng.sample(range(320), 5):
            scattered[at] = "other"
        rows.append((10 * g + 1, " ".join(scattered)))
        at = rng.randrange(260)
        rows.append((10 * g + 2, " ".join([*t[:at], *(rng.choice(words) for _ in range(30)), *t[at + 30 :]])))
        rows.append((10 * g + 3, " ".join(t[:285])))
        far = list(t)
        for at in range(0, 320, 12):
            far[at] = "far"
        rows.append((10 * g + 4, " ".join(far)))
    want = set(brute(rows).values())
    got = kept_of(spark, rows)
    assert want <= got and len(got - want) <= 1  # a pair is missed with a chance under 0.01
    assert len(want) == 80


def test_large_group_makes_few_pairs(spark):
    rng = random.Random(8)
    base = [f"v{rng.randrange(2000)}" for _ in range(200)]
    rows = []
    for i in range(300):
        t = list(base)
        for at in rng.sample(range(200), 2):
            t[at] = f"x{i}"
        rows.append((i, " ".join(t)))
    df = spark.createDataFrame(rows, "doc_id long, text string")
    s = N.Settings()
    texts = N.signatures(df, s, "doc_id", "text").select("k", "n", "fp", "keys")
    assert N.candidates(texts, s).count() <= (2 * s.bands + s.simhash.bits) * len(rows)
    assert kept_of(spark, rows) == {0}


def test_edges(spark):
    rows = [(1, None), (2, ""), (3, " \t"), (4, "One two"), (5, "one  TWO"), (6, "one three"), (7, "w " * 40000), (8, "w " * 40001), (None, "One two"), (9, "One two"), (9, "else")]
    df = spark.createDataFrame([(*r, "q", b"z") for r in rows], "doc_id long, text string, k string, sh binary")
    out = N.one_of_each(df).collect()
    assert sorted(str(r.doc_id) for r in out) == sorted(["1", "4", "6", "7", "None", "9", "9"])  # the least id of "else" is 9
    assert all(r.k == "q" for r in out)
    assert N.one_of_each(df.filter("false")).count() == 0


def test_signatures_are_those_of_the_definition():
    texts = ["a b c d e f", "A b c", "", "a b c d e f a b c d e f"]
    h, no = N.shingles(texts, 5)
    assert no.tolist() == [0, 0, 1, *[3] * 8]
    assert h[0] == h[3] and h[1] == h[4] and h[0] == h[9] and len(set(h.tolist())) == 7
    s = N.Settings()
    a, at = N._distinct(h, no, 4)
    keys = N.band_keys(a, at[[0, 1, 3]], s)
    assert keys.shape == (3, 32) and len({tuple(k) for k in keys.tolist()}) == 3
    ones = sum(int(x) >> 63 for x in a[: at[1]])
    assert (N.majority(a, at[[0, 1, 3]])[0][0] >> 7) == int(2 * ones > at[1])


def test_no_pair_of_a_mixed_bucket_is_lost(spark):
    """Pairs of near copies that share their one bucket with texts that are
    near none of them, and are neither neighbours in it nor near its leader."""
    rng = random.Random(5)
    common = [f"c{i}" for i in range(110)]
    rows = []
    for g in range(12):
        t = common + [f"g{g}-{rng.randrange(10**6)}" for _ in range(100)]
        rows += [(2 * g, " ".join(t)), (2 * g + 1, " ".join([*t, *(f"e{g}-{i}" for i in range(12))]))]
    got = {r.component for r in N.groups(spark.createDataFrame(rows, "doc_id long, text string"), N.Settings(bands=1, rows=1)).collect()}
    assert got == set(brute(rows).values()) == set(range(0, 24, 2))


def test_mixed_pairs_over_batches():
    import itertools

    import pyarrow as pa

    rng = random.Random(2)
    rows = sorted((rng.randrange(6), rng.randrange(10, 30), bytes([i]), rng.randrange(3)) for i in range(120))
    rows += [(9, 10, b"x", 1), (9, 11, b"y", 1)]
    batches = [pa.RecordBatch.from_pylist([dict(zip("key n k c".split(), r, strict=True)) for r in rows[i : i + 7]], pa.schema([("key", pa.int64()), ("n", pa.int32()), ("k", pa.binary()), ("c", pa.int64())])) for i in range(0, len(rows), 7)]
    got = sorted((r["a"], r["b"]) for b in N._mixed_pairs(iter(batches), 0.8, 16) for r in b.to_pylist())
    want = sorted((min(x[2], y[2]), max(x[2], y[2])) for x, y in itertools.combinations(rows, 2) if x[0] == y[0] and x[3] != y[3] and 25 * min(x[1], y[1]) >= 16 * max(x[1], y[1]))
    assert got == want


def test_links_of_a_mixed_bucket_without_its_pairs(spark, monkeypatch):
    """A bucket of a large component and many texts outside of it: rows by the
    members, whatever the blocks, and a link wherever some pair has one."""
    import struct

    import pyarrow as pa

    rng = random.Random(9)
    rows, sets = [], {}
    for i in range(160):
        k, c = bytes([i]), 1 if i < 110 else 2 + i // 4
        own = rng.sample(range(100), 80) if i % 10 else list(range(i % 20, 100))
        sets[k] = b"".join(struct.pack("<I", x) for x in sorted(own))
        rows.append((7 if i < 150 else 8, len(own), k, c))
    rows.sort()
    monkeypatch.setattr(N, "BLOCK_ROWS", 1000)
    schema = pa.schema([("key", pa.int64()), ("n", pa.int32()), ("k", pa.binary()), ("c", pa.int64())])
    batch = pa.RecordBatch.from_pylist([dict(zip("key n k c".split(), r, strict=True)) for r in rows], schema)
    assert sum(b.num_rows for b in N._mixed_rows(iter([batch]))) == len(rows)
    of = {r[2]: r[3] for r in rows}
    close = lambda p: N.similarity_of(sets[p["a"]], sets[p["b"]]) >= 0.8
    want = {frozenset([of[p["a"]], of[p["b"]]]) for b in N._mixed_pairs(iter([batch]), 0.8) for p in b.to_pylist() if close(p)}
    assert len(want) > 5
    for size in (1000, 7):
        monkeypatch.setattr(N, "BLOCK_ROWS", size)
        mixed = [tuple(r.values()) for b in N._mixed_rows(iter([batch])) for r in b.to_pylist()]
        cells = N._cells(spark.createDataFrame(mixed, "bucket long, k binary, c long, b int, home int, of int")).collect()
        if size == 1000:
            assert len(cells) == len(rows)
        met = [{"key": hash((r.bucket, r.x, r.y)) % 5, **r.asDict(), "sh": sets[bytes(r.k)]} for r in cells]  # cells that share a hash stay apart
        met.sort(key=lambda r: r["key"])
        kinds = pa.schema([("key", pa.int64()), ("bucket", pa.int64()), ("x", pa.int32()), ("y", pa.int32()), ("b", pa.int32()), ("k", pa.binary()), ("c", pa.int64()), ("sh", pa.binary())])
        batches = [pa.RecordBatch.from_pylist(met[i : i + 50], kinds) for i in range(0, len(met), 50)]
        found = [p for b in N._cell_links(iter(batches), 0.8) for p in b.to_pylist()]
        assert all(close(p) for p in found)
        assert {frozenset([of[p["a"]], of[p["b"]]]) for p in found} == want
