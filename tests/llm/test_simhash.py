import random
from collections import Counter

import pytest
import xxhash
from pyspark.sql import functions as F

import edgeconn.llm.simhash as S
from edgeconn.llm.queries import op8_simhash_near_dedup


def brute_fp(text):
    w = [x for x in "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in text or "").encode().split()]
    if not w:
        return 0
    sh = [b" ".join(w[i : i + 3]) for i in range(len(w) - 2)] or [b" ".join(w)]
    n = Counter()
    for s in sh:
        h = xxhash.xxh64_intdigest(s, 42)
        for b in range(64):
            n[b] += h >> b & 1
    return sum(1 << b for b in range(64) if 2 * n[b] > len(sh))


def brute_components(fps, most):
    """fps: [(id, int)]."""
    comp = {}
    todo = sorted(fps)
    for i, f in todo:
        if i in comp:
            continue
        comp[i], front = i, [f]
        while front:
            g = front.pop()
            for j, h in todo:
                if j not in comp and (g ^ h).bit_count() <= most:
                    comp[j] = i
                    front.append(h)
    return comp


def test_contract_query_equals_brute_force(spark, small):
    rows = op8_simhash_near_dedup(spark, small).collect()
    docs = {r.doc_id: r.text for r in spark.read.parquet(f"{small}/documents.parquet").collect()}
    fps = {i: brute_fp(t) for i, t in docs.items()}
    assert {r.doc_id: int(r.fingerprint, 16) for r in rows} == fps
    want = brute_components(list(fps.items()), 3)
    assert {r.doc_id: r.component_id for r in rows} == want


@pytest.mark.parametrize("hot", [1 << 14, 3])
def test_links_keep_every_component(spark, monkeypatch, hot):
    monkeypatch.setattr(S, "HOT", hot)
    rng = random.Random(5)
    fps = []
    for _ in range(12):
        base = rng.getrandbits(64)
        for _ in range(rng.choice([1, 2, 30])):
            base ^= sum(1 << b for b in rng.sample(range(64), rng.randint(0, 4)))
            fps.append(base)
    fps = list(dict.fromkeys(fps))
    df = spark.createDataFrame([(bytearray(f.to_bytes(8, "big")),) for f in fps], "fp binary")
    got = S.star_components(S.links(df, S.SimHash()), "a", "b").collect()
    comp = {bytes(r.v): bytes(r.comp) for r in got}
    mine = {f: comp.get(f.to_bytes(8, "big"), f.to_bytes(8, "big")) for f in fps}
    assert {f: int.from_bytes(c, "big") for f, c in mine.items()} == brute_components([(f, f) for f in fps], 3)


def test_edges_of_the_input(spark):
    rows = [(1, None, "x"), (2, "", "x"), (3, " \t\n", "x"), (4, "One two", "x"), (4, "One two", "x"), (None, "one TWO", "x"), (7, "w " * 40000, "x")]
    df = spark.createDataFrame(rows, "doc_id long, text string, fp string")
    out = sorted((str(r.id), r.fp == bytes(8), r.component) for r in S.near_duplicates(df).collect())
    assert out == sorted([("1", True, 1), ("2", True, 1), ("3", True, 1), ("4", False, 4), ("4", False, 4), ("None", False, 4), ("7", False, 7)])
    assert S.near_duplicates(df.filter("false")).count() == 0


