"""Queries against plain recomputations, and odd tables: nulls, empty and very
long texts, repeated rows, empty tables, extra columns of clashing names."""

import math
import random
from bisect import bisect_left

import numpy as np
import pytest
import zstandard

from edgeconn.llm import lm, pieces, pii, sharding, toxicity
from edgeconn.llm.queries import op2_token_rollup, op6_hilbert_shards
from edgeconn.plans.staging import new_path
from tests.llm.test_models import made_up


def test_rollup_query_on_odd_tables(spark):
    rows = [
        (1, "s", "en", "a b"), (2, "s", "en", "a b"), (3, "t", "en", "a b"), (4, None, None, None), (None, None, "en", ""),
        (5, "s", "en", "x,y"), (5, "s", "en", "x,y"), (6, "s", "en", "w " * 30000),
    ]
    docs = spark.createDataFrame([(*r, 7) for r in rows], "doc_id long, source string, lang string, text string, n_docs long")
    for df, want in ((docs, {("s", "en", "words-2", 3, 30005), (None, None, "words-2", 1, 0)}), (docs.filter("false"), set())):
        folder = new_path(spark, "odd")
        df.write.parquet(f"{folder}/documents.parquet")
        assert {tuple(r) for r in op2_token_rollup(spark, folder).collect()} == want


def test_window_lengths_equal_plain_compression():
    rng = random.Random(3)
    texts = lambda k, bad: [made_up(rng, rng.randint(40, 200), bad) for _ in range(k)]
    m = toxicity.fit(texts(60, 4), texts(120, 0), 0.3)

    def size(content, window):
        d = zstandard.ZstdCompressionDict(content, dict_type=zstandard.DICT_TYPE_RAWCONTENT)
        d.precompute_compress(level=m.level)
        return len(zstandard.ZstdCompressor(level=m.level, dict_data=d, write_content_size=False, write_checksum=False, write_dict_id=False).compress(window))

    for text in ["", "a", *texts(3, 0), *texts(3, 4), made_up(rng, 3000, 9)]:
        b = toxicity.fold(text)
        gain = sorted((size(m.ordinary, b[i : i + m.window]) - size(m.toxic, b[i : i + m.window]) for i in range(0, len(b), m.window)), reverse=True)
        share = [sum(g >= x for g in gain) / len(gain) for x in (2, 4, 6)]
        got = toxicity.features(m, [toxicity.fold("before"), b, toxicity.fold("after")])[1]
        assert got[0] == min(gain[0], 8) and got[1] == pytest.approx(np.mean(gain[:3])) and got[2] == pytest.approx(np.mean(gain[:6]))
        assert got[3] == pytest.approx(np.mean(gain)) and list(got[4:7]) == pytest.approx(share) and got[9] == pytest.approx(math.log(len(gain)))


def test_shards_equal_a_plain_sort(spark, small):
    docs = spark.read.parquet(f"{small}/documents.parquet").select("doc_id", "source", "lang", "text").collect()
    cells = 1 << sharding.BITS

    def codes(values):
        order = sorted(values, key=lambda v: (v is not None, v or ""))
        keys = [(v is not None, v or "") for v in order]
        return [bisect_left(keys, (v is not None, v or "")) * cells // len(order) for v in values]

    got = {r.doc_id: r for r in op6_hilbert_shards(spark, small).collect()}
    size = [got[d.doc_id]["size"] for d in docs]
    depth = [min(max(math.floor(3 * (math.log(s / 8) / math.log(2))), 0), cells - 1) for s in size]
    at = sharding.hilbert_index([np.array(codes([d.source for d in docs])), np.array(codes([d.lang for d in docs])), np.array(depth)], sharding.BITS)
    order = sorted((int(c), got[d.doc_id].text_crc32, d.doc_id) for c, d in zip(at, docs, strict=True))
    base, more = divmod(len(order), 24)
    place = 0
    for n in range(24):
        for slot in range(base + (n < more)):
            r = got[order[place][2]]
            assert (r.curve, r.shard, r.slot) == (order[place][0], n, slot)
            place += 1


def test_language_model_on_odd_tables(spark):
    rows = [(None, "red cat"), (1, None), (1, "red cat"), (1, "red cat"), (2, "cat " * 60000), (3, "never seen")]
    df = spark.createDataFrame([(*r, "x", 5) for r in rows], "doc_id long, text string, word string, score long")
    m = lm.train(df.filter("doc_id is null or doc_id < 3"), lm.Settings(single=20, groups=4, table=6, classes=3, passes=2))
    out = lm.score(df, m, ["doc_id"]).collect()
    assert sorted((r.doc_id or 0, r.n_tokens, r.n_known) for r in out) == [(0, 3, 3), (1, 1, 1), (1, 3, 3), (1, 3, 3), (2, 60001, 60001), (3, 3, 1)]
    assert all(math.isfinite(r.score) and r.score < 0 for r in out)
    same = {r.score for r in out if r.n_tokens == 3 and r.n_known == 3}
    assert max(same) - min(same) < 1e-9
    assert lm.score(df.filter("false"), m, ["doc_id"]).count() == 0


def test_pseudonyms_on_odd_tables(spark):
    card = "4111 1111 1111 1111"
    rows = [(1, f"pay {card}"), (2, f"{card} again"), (2, f"{card} again"), (None, None), (3, "pad " * 50000 + card)]
    df = spark.createDataFrame([(*r, "x") for r in rows], "doc_id long, text string, kinds string")
    out = pii.pseudonymise(df).collect()
    assert len(out) == 5
    new = {r.text[-len(card):] if r.doc_id in (1, 3) else r.text[: len(card)] for r in out if r.text}
    assert len(new) == 1 and card not in new  # equal values stay linked
    assert pii.pseudonymise(df.filter("false")).count() == 0


def test_pieces_on_odd_tables(spark):
    rows = [(1, "ab cd"), (1, "ab cd"), (None, None), (2, "▁ ▁"), (3, "cd " * 70000)]
    df = spark.createDataFrame([(*r, "x", "y") for r in rows], "doc_id long, text string, ids string, id string")
    out = pieces.encode_decode(df).collect()
    sp = pieces.ChunkTable(pieces.model_bytes(pieces.default_model())).sp
    want = sorted((i or 0, sp.encode(t or ""), sp.decode(sp.encode(t or ""))) for i, t in rows)
    assert sorted((r.id or 0, list(r.ids), r.decoded) for r in out) == want
    assert pieces.encode_decode(df.filter("false")).count() == 0


def test_arrow_batches_are_bounded_by_bytes(spark):
    import pyarrow as pa

    from edgeconn.llm import common

    def rows(batches):
        for b in batches:
            yield pa.RecordBatch.from_pydict({"n": [b.num_rows]})

    before = spark.conf.get(common._BATCH, None)
    try:
        for held, want in ((None, common.BATCH_BYTES), ("1k", 1024), ("64MB", common.BATCH_BYTES)):
            spark.conf.unset(common._BATCH) if held is None else spark.conf.set(common._BATCH, held)
            common.small_batches(spark)
            assert common._bytes(spark.conf.get(common._BATCH)) == want
        got = spark.range(3000).selectExpr("repeat('x', 10000) AS t").coalesce(1).mapInArrow(rows, "n long").collect()
        assert sum(r.n for r in got) == 3000 and max(r.n for r in got) * 10_000 < 2 * common.BATCH_BYTES
    finally:
        spark.conf.unset(common._BATCH) if before is None else spark.conf.set(common._BATCH, before)
