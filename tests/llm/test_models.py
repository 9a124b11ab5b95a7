"""Toxicity, language model, PII, SentencePiece and the pipeline."""

import hashlib
import math
import random
from collections import Counter
from zlib import crc32

import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from edgeconn.llm import lm, pieces, pii, toxicity
from edgeconn.llm.queries import op3_toxicity, op7_brown_lm, op9_pii, op10_sentencepiece


def made_up(rng, n, bad):
    base = [f"{a}{b}" for a in ("th", "en", "or", "ti") for b in ("an", "es", "ing", "ble", "ou")]
    words = [rng.choice(base) + rng.choice(["", "", "ed", "ly"]) for _ in range(n)]
    for _ in range(bad):
        words[rng.randrange(n)] = rng.choice(["grumblefutz", "snorkwaddle", "blitherpox"])
    return " ".join(words)


def test_toxicity_learns_planted_words():
    rng = random.Random(1)
    texts = lambda k, bad: [made_up(rng, rng.randint(40, 300), bad) for _ in range(k)]
    m = toxicity.fit(texts(150, 4), texts(300, 0), 0.3)
    score = lambda ts: toxicity.probabilities(m, toxicity.features(m, [toxicity.fold(t) for t in ts]))
    assert (score(texts(80, 4)) >= 0.5).mean() > 0.9
    assert (score(texts(80, 0)) < 0.5).mean() > 0.95
    assert 0 <= score([""])[0] < 0.5
    assert toxicity.fit([], ["a"], 0.0).prior == 0.0


def test_toxicity_query(spark, small):
    rows = op3_toxicity(spark, small).collect()
    assert len(rows) == 200
    for r in rows:
        assert r.held_out == (crc32(str(r.doc_id).encode()) % 5 == 0) and 0 <= r.score <= 1 and r.predicted == int(r.score >= 0.5)
    odd = spark.createDataFrame([(None, None, "q"), (1, "", "q"), (1, "z" * 99999, "q")], "doc_id long, text string, score string")
    model = toxicity.train(odd, spark.createDataFrame([], "doc_id long, toxic int"))
    assert [r.score for r in toxicity.score(odd, model).collect()] == [0.0] * 3
    assert toxicity.without_toxic(odd, model).count() == 3


def words_of(text):
    return (text or "").encode().lower().split()


def test_lm_counts_and_base_equal_plain_version(spark, small, monkeypatch):
    real = lm.train
    monkeypatch.setattr(lm, "train", lambda t: real(t, lm.Settings(single=200, groups=50, table=300, classes=8, passes=3)))
    rows = {r.doc_id: r for r in op7_brown_lm(spark, small).collect()}
    docs = {r.doc_id: r.text for r in spark.read.parquet(f"{small}/documents.parquet").collect()}
    train = [t for i, t in docs.items() if crc32(str(i).encode()) % 10]
    c = Counter(w for t in train for w in words_of(t))
    ends, n, v = len(train), sum(c.values()) + len(train), len(c) + 1
    for i, t in docs.items():
        r, w = rows[i], words_of(t)
        assert (r.n_tokens, r.train_tokens, r.held_out) == (len(w) + 1, n, crc32(str(i).encode()) % 10 == 0)
        assert r.n_known == sum(c[x] > 0 for x in w) + 1
        base = sum(math.log10((k + 0.1) / (n + 0.1 * (v + 1))) for k in [*(c[x] for x in w), ends])
        assert r.base_score == pytest.approx(base, abs=1e-6)
    held = [r for r in rows.values() if r.held_out]
    assert sum(r.score for r in held) > sum(r.base_score for r in held)


def test_lm_is_a_distribution_and_exchange_gains(spark):
    texts = ["red cat runs", "blue dog runs", "red dog sits", "blue cat sits", "", "red cat sits slowly"] * 5
    df = spark.createDataFrame([(t,) for t in texts] + [(None,)], "text string")
    m = lm.train(df, lm.Settings(single=20, groups=4, table=6, classes=3, passes=4))
    assert m.trace[-1] >= m.trace[0] - 1e-9
    words = sorted({w for t in texts for w in t.split()})
    docs = spark.createDataFrame([(w, w) for w in words], "id string, text string")
    got = {r.id: r for r in lm.score(docs, m, ["id"]).collect()}
    # p(w) after an end, all words, the end and each class's unseen slot, is 1
    total = sum(10 ** (r.score - float(m.step[m.classes[unit_of(m, w)]][3]) - (math.log10(m.ends + 0.1) - float(m.room[3]))) for w, r in got.items())
    first = sum(10 ** float(m.step[3][k]) * 0.1 / 10 ** float(m.room[k]) for k in range(4))
    end = 10 ** (float(m.step[3][3]) + math.log10(m.ends + 0.1) - float(m.room[3]))
    assert total + first + end == pytest.approx(1)
    assert lm.train(df.filter("false")).n == 0


def unit_of(m, w):
    s, names = m.settings, m.head.to_pylist()
    return names.index(w) if w in names[: s.single] else s.single + lm.group_of(w.encode(), s.groups)


KEYED = pii.Pseudonymiser(pii.Settings())


@pytest.mark.parametrize("size", [1, 2, 7, 10, 100, 257])
def test_feistel_is_a_bijection(size):
    net = pii.Feistel(b"k", "t", size)
    out = [net.apply(x) for x in range(size)]
    assert sorted(out) == list(range(size)) and [net.invert(y) for y in out] == list(range(size))


@settings(max_examples=60, deadline=None)
@given(st.text("0123456789", min_size=12, max_size=18))
def test_cards_stay_valid(body):
    number = body + str(pii.luhn_digit(body))
    new = KEYED.replace("card", number)
    if len(set(number)) > 1:
        assert new != "" and len(new) == len(number) and pii.luhn_digit(new[:-1]) == int(new[-1])
        assert pii._only(KEYED.replace("card", number[:4] + " " + number[4:])) == new
    wrong = body + str((int(number[-1]) + 1) % 10)
    assert KEYED.replace("card", wrong) is None


def test_formats():
    text = "Call +1 (017) 555-7713 or 555-123-4567, card 4111 1111 1111 1111, ip 10.0.0.250, born 1984-02-29 or 29.2.1984, ssn 123-45-6789, mail Jo.72@mail3.example.com, token = \"04dbebab91ab85687d33eeaaf9ac699e1188f962\", GB82 WEST 1234 5698 7654 32."
    new, kinds = KEYED.text(text)
    assert kinds == ["phone", "phone", "card", "ip", "date", "date", "ssn", "email", "secret", "iban"]
    assert len(new) == len(text)
    for gone in ("555-7713", "4111 1111", "10.0.0.250", "1984-02-29", "123-45-6789", "Jo.72", "04dbebab", "1234 5698"):
        assert gone not in new
    assert KEYED.text(new)[1] == kinds  # what comes out is valid again
    assert KEYED.text(text)[0] == new and pii.Pseudonymiser(pii.Settings(key=b"other")).text(text)[0] != new
    same, none = KEYED.text("v1.2.3 costs 4111 1111 1111 1112 on 2023-02-30 at 300.1.1.1, 000-12-3456")
    assert none == [] and same.startswith("v1.2.3")


def iban(country, body):
    return f"{country}{98 - int(''.join(str(int(c, 36)) for c in body + country + '00')) % 97:02d}{body}"


def test_neighbouring_values_do_not_hide_each_other():
    at = iban("AT", "1904300234573201")
    spaced = " ".join(at[i : i + 4] for i in range(0, 20, 4))
    for text, values, kinds in [
        ("123-45-6789 456-78-1234", ["123-45-6789", "456-78-1234"], ["ssn", "ssn"]),
        ("4465758382889437 123", ["4465758382889437"], ["card"]),
        ("4465-7583-8288-9437-123", ["4465-7583-8288-9437"], ["card"]),
        ("12 4465758382889437 123", ["4465758382889437"], ["card"]),
        ("555-123-4567 2025", ["555-123-4567"], ["phone"]),
        ("123-45-6789 123456", ["123-45-6789"], ["ssn"]),
        (f"{spaced} PAID on", [spaced], ["iban"]),
        (f"{at} NOW", [at], ["iban"]),
        ("DE12 4111 1111 1111 1111", ["4111 1111 1111 1111"], ["card"]),
    ]:
        new, got = KEYED.text(text)
        assert got == kinds and len(new) == len(text) and not any(v in new for v in values), text


def test_pii_query_and_edges(spark, small):
    rows = op9_pii(spark, small).collect()
    docs = {r.doc_id: r.text for r in spark.read.parquet(f"{small}/documents.parquet").collect()}
    assert len(rows) == len(docs)
    for r in rows:
        assert len(r.text) == len(docs[r.doc_id]) and (r.text != docs[r.doc_id]) == (r.n_replaced > 0)
    odd = spark.createDataFrame([(1, None, "x"), (None, "", "y"), (2, "ip 8.8.8.8", "z")], "doc_id long, text string, kinds string")
    out = {r.doc_id: r for r in pii.pseudonymise(odd).collect()}
    assert out[1].text is None and out[None].text == "" and out[2].kinds == ["ip"]


MODEL = pieces.ChunkTable(pieces.model_bytes(pieces.default_model()))


@settings(max_examples=150, deadline=None)
@given(st.text(st.one_of(st.sampled_from(" ▁ab\n\t."), st.characters(blacklist_categories=["Cs"])), max_size=60))
def test_chunks_give_the_librarys_ids(text):
    chunks = MODEL.chunks(text)
    MODEL.learn(set(chunks))
    ids = MODEL.sp.encode(text)
    assert MODEL.encode(chunks) == ids and MODEL.decode(chunks) == MODEL.sp.decode(ids)


def test_sentencepiece_query(spark, small):
    rows = {r.doc_id: r for r in op10_sentencepiece(spark, small).collect()}
    docs = spark.read.parquet(f"{small}/documents.parquet").collect()
    for d in docs:
        ids = MODEL.sp.encode(d.text or "")
        r = rows[d.doc_id]
        assert r.n_tokens == len(ids) and r.ids_sha256 == hashlib.sha256(",".join(map(str, ids)).encode()).hexdigest()
        assert r.decoded_sha256 == hashlib.sha256(MODEL.sp.decode(ids).encode()).hexdigest()
    odd = spark.createDataFrame([(None, None), (1, ""), (2, "ab " * 50000)], "doc_id long, text string")
    got = {r.id: r for r in pieces.encode_decode(odd).collect()}
    assert got[None].n_tokens == 0 and got[1].ids == [] and got[2].decoded == "ab " * 50000


def test_pipeline_stages(spark, small):
    import corpus_pipeline as C

    docs = spark.read.parquet(f"{small}/documents.parquet")
    assert [n for n, _ in C.STAGES] == ["toxicity", "simhash_near_dedup", "benchmark_decontamination", "pii", "sentencepiece"]
    for step in (C.drop_toxic, C.drop_near_copies, C.drop_leaks, C.hide_private):
        out = step(spark, docs, small)
        assert out.columns == docs.columns and out.count() <= docs.count()
    last = C.run(spark, small)
    assert last.columns[0] == "doc_id" and 0 < last.count() <= docs.count()
    assert C.run(spark, small).exceptAll(last).isEmpty()


def test_pipeline_equals_its_operators_one_by_one(spark, small):
    """Every stage's decisions, made text by text without Spark."""
    import corpus_pipeline as C
    from edgeconn.llm import decontaminate
    from tests.llm.test_nearcopies import brute

    read = lambda n: spark.read.parquet(f"{small}/{n}.parquet")
    docs = {r.doc_id: r.text or "" for r in read("documents").collect()}
    model = toxicity.train(read("documents"), read("labels"))
    p = toxicity.probabilities(model, toxicity.features(model, [toxicity.fold(t) for t in docs.values()])) if model.weights else [0] * len(docs)
    docs = {i: t for (i, t), x in zip(docs.items(), p, strict=True) if x < 0.5}
    stay = set(brute(docs.items()).values())
    docs = {i: t for i, t in docs.items() if i in stay}
    probes = decontaminate.Probes([(r.item_id, r.text) for r in read("benchmark").collect()], decontaminate.Settings())
    docs = {i: KEYED.text(t)[0] for i, t in docs.items() if not decontaminate.find(probes, [t])}
    rows = {r.doc_id: r for r in C.run(spark, small).collect()}
    assert set(rows) == set(docs)
    for i, t in docs.items():
        ids = MODEL.sp.encode(t)
        assert rows[i].n_tokens == len(ids) and bytes(rows[i].ids) == b"".join(x.to_bytes(2, "little") for x in ids)
        assert rows[i].decoded_sha256 == hashlib.sha256(MODEL.sp.decode(ids).encode()).hexdigest()


def test_stages_on_odd_tables(spark, small):
    import corpus_pipeline as C

    rows = [(1, None, "x"), (2, "", "y"), (3, "long " * 60000, "z"), (3, "long " * 60000, "z"), (None, "ip 8.8.8.8", "z"), (4, "ip 8.8.8.8 again", "k")]
    docs = spark.createDataFrame([(*r, "en", "s", 5) for r in rows], "doc_id long, text string, n_replaced string, lang string, source string, n_chars long")
    for _, step in C.STAGES[:-1]:
        out = step(spark, docs, small)
        assert out.columns == docs.columns
        assert step(spark, docs.filter("false"), small).count() == 0
        names = sorted(str(r.doc_id) for r in out.collect())
        assert names == (["1", "3", "3", "4", "None"] if step is C.drop_near_copies else ["1", "2", "3", "3", "4", "None"])
    ids = C.to_ids(spark, docs, small)
    assert ids.count() == 6 and C.to_ids(spark, docs.filter("false"), small).count() == 0
