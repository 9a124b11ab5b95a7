"""Chat, token rollups, decontamination, fingerprints and shards."""

import hashlib
import random
import zlib

import numpy as np
import pytest
from pyspark.sql import functions as F

from edgeconn.llm import chat, decontaminate, fingerprint, sharding, tokencounts
from edgeconn.llm.queries import op5_syncmer_fingerprints, op6_hilbert_shards
from edgeconn.plans.staging import new_path


# Chat.

def test_chat_pieces_concatenate_to_each_seat(spark):
    rows = [(1, 0, "system", "be kind"), (1, 1, "ann", "hi"), (1, 2, "bob", None), (1, 3, "ann", "bye"), (2, 0, "system", "alone"), (None, 5, None, "lost"), (None, 5, None, "lost")]
    df = spark.createDataFrame([(*r, "x") for r in rows], "conv_id long, turn long, role string, text string, piece string")
    out = chat.perspectives(df).collect()
    seats = {}
    for r in out:
        if r.conv_id:
            seats.setdefault((r.conv_id, r.perspective), []).append(r)
    assert set(seats) == {(1, "ann"), (1, "bob")}
    for (_, who), pieces in seats.items():
        pieces.sort(key=lambda r: r.seq)
        text = "".join(p.piece for p in pieces)
        assert text.startswith("<|system|>\nbe kind<|end|>\n")
        for p in pieces:
            assert text[p.char_start :].startswith(p.piece)
            assert (p.train_start is not None) == (p.name == who) == (p.chat_role == "assistant")
            if p.train_start is not None:
                body = next(t or "" for _, n, s, t in rows if s == who and n == p.turn)
                assert text[p.train_start : p.train_end] == f"{body}<|end|>\n"
            elif p.name != "system":
                assert p.piece.startswith(f"<|user:{p.name}|>")
    lost = [r for r in out if r.conv_id is None]
    assert len(lost) == 2 and all(r.perspective == "unknown" and r.seq == 0 for r in lost)
    assert chat.perspectives(df.filter("false")).count() == 0


# Token counts.

def test_rollup_is_idempotent_and_signed(spark):
    store = tokencounts.RollupStore(spark, new_path(spark, "t"))
    assert store.totals().count() == 0
    docs = spark.createDataFrame([("a", "en", 3), ("a", "en", 4), (None, None, None)], "source string, lang string, c long")
    c = F.col("c")
    assert store.commit("1", tokencounts.insert(docs, "v1", c)) and not store.commit("1", tokencounts.insert(docs, "v1", c))
    key = lambda: sorted(str(tuple(r)) for r in store.totals().collect())
    assert key() == sorted(["('a', 'en', 'v1', 2, 7)", "(None, None, 'v1', 1, 0)"])
    store.commit("2", tokencounts.delete(docs.filter("c = 3 OR c IS NULL"), "v1", c))
    store.commit("3", tokencounts.revise(docs.filter("c = 4"), ("v1", c), ("v2", c + 1)))
    store.commit("3", tokencounts.revise(docs, ("v1", c), ("v2", c)))
    assert key() == ["('a', 'en', 'v2', 1, 5)"]


def test_token_counts(spark):
    texts = ["", "  ", "a", " a  b\tc\n", "x,y! z", "é　b"]
    rows = spark.createDataFrame([(t,) for t in texts], "t string").select(tokencounts.words(F.col("t")), tokencounts.words_and_marks(F.col("t"))).collect()
    assert [r[0] for r in rows] == [len(t.encode().split()) for t in texts]
    assert [r[1] for r in rows] == [0, 0, 1, 3, 5, 1]


# Decontamination.

def distance_inside(text, probe):
    """Least edits of the probe against any part of the text."""
    row = [0] * (len(text) + 1)
    for i, c in enumerate(probe, 1):
        new = [i]
        for j, x in enumerate(text, 1):
            new.append(min(row[j - 1] + (x != c), row[j] + 1, new[j - 1] + 1))
        row = new
    return min(row)


@pytest.mark.parametrize("seed", range(12))
def test_leaks_equal_brute_force(seed):
    rng = random.Random(seed)
    word = lambda: "".join(rng.choice("abcdefgh") for _ in range(rng.randint(2, 7)))
    items = [(i, " ".join(word() for _ in range(rng.randint(15, 40)))) for i in range(6)]
    s = decontaminate.Settings()
    probes = decontaminate.Probes(items, s)
    texts = []
    for _ in range(10):
        t = [word() for _ in range(60)]
        if rng.random() < 0.8:
            body = list(rng.choice(items)[1])
            for _ in range(rng.randint(0, 12)):
                at = rng.randrange(len(body))
                kind = rng.random()
                if kind < 0.4:
                    body[at] = rng.choice("abcdefgh")
                elif kind < 0.7:
                    del body[at]
                else:
                    body.insert(at, rng.choice("abcdefgh"))
            t.insert(rng.randrange(60), "".join(body).upper() if rng.random() < 0.3 else "".join(body))
        texts.append(" ".join(t))
    got = {(d, p): e for d, p, _, _, e in decontaminate.find(probes, texts)}
    for d, t in enumerate(texts):
        text = "".join(map(chr, decontaminate.normalise(t)[0]))
        for p, codes in enumerate(probes.codes):
            best = distance_inside(text, "".join(map(chr, codes)))
            if best <= probes.budget[p]:
                assert got.get((d, p)) == best
            else:
                assert (d, p) not in got


def test_leak_places_and_edges(spark):
    item = "The quick brown fox jumps over the lazy dog, and then it sleeps for a whole long day."
    docs = spark.createDataFrame([(1, "Well: " + item.upper() + " Yes."), (2, None), (3, ""), (4, item[:40]), (5, "pad " * 30000 + item), (5, item)], "doc_id long, text string")
    bench = spark.createDataFrame([(7, item, "x"), (8, None, "x"), (9, "tiny", "x")], "item_id long, text string, start string")
    out = decontaminate.leaks(docs, bench).collect()
    assert sorted((r.id, r.edits) for r in out) == [(1, 0), (5, 0), (5, 0)]
    one = next(r for r in out if r.id == 1)
    assert one.item == 7 and ("Well: " + item.upper() + " Yes.")[one.start : one.end] == item.upper()[:-1]
    small = decontaminate.Settings(broadcast_chars=40)  # several passes over the documents
    assert sorted(r.id for r in decontaminate.leaks(docs, bench, small).collect()) == [1, 5, 5]
    assert sorted(r.doc_id for r in decontaminate.without_leaks(docs, bench, small).collect()) == [2, 3, 4]
    assert decontaminate.leaks(docs, bench.filter("false")).count() == decontaminate.leaks(docs.filter("false"), bench).count() == 0


def test_verbatim_parts_are_found_at_every_offset():
    rng = random.Random(7)
    word = lambda: "".join(rng.choice("abcdefgh") for _ in range(rng.randint(2, 7)))
    for size in (70, 96, 300):
        item = " ".join(word() for _ in range(100))[:size].strip()
        probes = decontaminate.Probes([(3, item)], decontaminate.Settings())
        texts = [f"zzzz {item[i : i + 63]} zzzz" for i in range(len(item) - 62)]
        found = decontaminate.find(probes, texts)
        assert {d for d, _, _, _, e in found if e == 0} == set(range(len(texts)))
        assert decontaminate.without_repeats(probes, found)
        assert not decontaminate.find(probes, [item[:40]])


def test_each_place_of_a_band_is_found():
    item = ("abcd " * 10).strip()
    probes = decontaminate.Probes([(1, item)], decontaminate.Settings())
    places = [(s, e) for _, p, s, e, _ in decontaminate.find(probes, [" ".join([item] * 3)]) if p == 0]
    assert {(0, 49), (50, 99), (100, 149)} <= set(places)


# Fingerprints.

def test_closed_syncmers_are_those_of_the_definition():
    s = fingerprint.Settings()
    rng = random.Random(2)
    text = "".join(rng.choice("abcdé ") for _ in range(500))
    h, at = fingerprint.anchors(text, s)
    want = []
    for i in range(len(text) - s.k + 1):
        inner = [int(fingerprint._rolling(np.array([ord(c) for c in text[i + j : i + j + s.s]], np.uint64), s.s)[0]) for j in range(s.k - s.s + 1)]
        if min(inner) in (inner[0], inner[-1]):
            want.append(i)
    assert at.tolist() == want
    again, place = fingerprint.anchors("other words before " + text, s)
    assert set(h.tolist()) <= set(again.tolist())


def test_fingerprint_query_equals_plain_version(spark, small):
    rows = {r.doc_id: r for r in op5_syncmer_fingerprints(spark, small).collect()}
    docs = sorted(((r.doc_id, r.text or "") for r in spark.read.parquet(f"{small}/documents.parquet").collect()), reverse=True)
    s = fingerprint.Settings()
    assert len(rows) == len(docs)
    for n, (i, t) in enumerate(docs):
        nxt = docs[(n + 1) % len(docs)][1]
        e = t[: len(t) - len(t) // 2] + nxt[: len(t) // 2]
        r = rows[i]
        assert r.n_chars == len(t) and r.edited_sha256 == hashlib.sha256(e.encode()).hexdigest()
        assert r.fingerprint == fingerprint.encode(fingerprint.sketch(t, s)) and r.edited_fingerprint == fingerprint.encode(fingerprint.sketch(e, s))
        assert r.near_next == fingerprint.likeness(fingerprint.decode(r.fingerprint), fingerprint.sketch(nxt, s), s)
        assert 0 <= r.near_edited <= 1
    long = [r for r in rows.values() if r.n_chars > 1000]
    assert np.mean([r.near_edited > r.near_next for r in long]) > 0.9


@pytest.mark.parametrize("ranges", [1, 3, 40])
def test_neighbours_over_any_ranges(spark, ranges):
    rows = [(5, "five five five five five"), (5, "a five"), (None, "none at all"), (9, ""), (1, None), (3, "x" * 70000)]
    df = spark.createDataFrame([(*r, "y") for r in rows], "doc_id long, text string, fingerprint string")
    out = fingerprint.edited_neighbours(df, ranges=ranges).collect()
    order = sorted(rows, key=lambda r: (r[0] is None, -(r[0] or 0), r[1] or ""))
    for n, (i, t) in enumerate(order):
        t, nxt = t or "", order[(n + 1) % len(order)][1] or ""
        e = t[: len(t) - len(t) // 2] + nxt[: len(t) // 2]
        assert hashlib.sha256(e.encode()).hexdigest() in {r.edited_sha256 for r in out if r.id == i}
    assert len(out) == len(rows)
    assert fingerprint.edited_neighbours(df.filter("doc_id = 9"), ranges=ranges).first().near_next == 1.0
    assert fingerprint.edited_neighbours(df.filter("false"), ranges=ranges).count() == 0


# Shards.

def test_hilbert_curve_visits_every_cell_by_single_steps():
    for dims, bits in ((2, 4), (3, 3)):
        cells = np.stack(np.meshgrid(*[np.arange(1 << bits)] * dims, indexing="ij")).reshape(dims, -1)
        at = sharding.hilbert_index(list(cells), bits)
        assert sorted(at.tolist()) == list(range(1 << (bits * dims)))
        walk = cells[:, np.argsort(at)]
        assert (np.abs(np.diff(walk, axis=1)).sum(0) == 1).all()


def test_shards_are_even_runs(spark, small):
    rows = op6_hilbert_shards(spark, small).collect()
    docs = {r.doc_id: r.text or "" for r in spark.read.parquet(f"{small}/documents.parquet").collect()}
    by = {}
    for r in rows:
        assert r["size"] == len(docs[r.doc_id].encode()) + 8 and r.text_crc32 == zlib.crc32(docs[r.doc_id].encode())
        by.setdefault(r.shard, []).append(r)
    assert len(rows) == len(docs) and set(by) <= set(range(24))
    assert max(map(len, by.values())) - min(map(len, by.values())) <= 1
    last = -1
    for n in sorted(by):
        slots = sorted(by[n], key=lambda r: r.slot)
        assert [r.slot for r in slots] == list(range(len(slots)))
        for r in slots:
            assert r.curve >= last
            last = r.curve


def test_shards_of_odd_tables(spark):
    rows = [(1, "a", None, None)] * 7 + [(None, None, "s", "en"), (2, "é", "s", "en")]
    df = spark.createDataFrame([(*r, 1) for r in rows], "doc_id long, text string, source string, lang string, shard int")
    out = sharding.shard(df, 4).collect()
    assert sorted(sum(1 for r in out if r.shard == i) for i in range(4)) == [2, 2, 2, 3]
    assert sharding.shard(df.filter("false"), 4).count() == 0
    assert sorted(r.shard for r in sharding.shard(df.limit(3), 24).collect()) == [0, 1, 2]


