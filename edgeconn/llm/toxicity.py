"""Toxicity by compression distance to two zstandard dictionaries.

A text is cut into short windows; each is compressed once against a dictionary
trained on toxic text and once against one trained on ordinary text. Where the
first makes a window shorter, the window reads like toxic text. How often and
by how much it does so over all windows of a text is turned into a probability
by a logistic calibration fitted on labelled texts the dictionaries never saw.

Both dictionaries end in the same block of common ordinary text, so common
matter costs the same under either and cancels; before it each has the
segments that its class uses significantly more than the other does. With few
labels hardly any segment is significant; the toxic dictionary then takes its
surest ones all the same, and the calibration decides what they are worth.

The library's own trainer is not used: on these windows it keeps what is
frequent in a class, which both classes share (figures in the README).
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass, field

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from edgeconn.llm.common import blocks, held_out, keep_rows, text_or_empty


@dataclass(frozen=True)
class Settings:
    """per_class: labelled texts of each class that a fit reads at most (the
    bound of the training sample). window: bytes. lengths: of segments.
    segments: per length. significance: least z value of a segment. fill:
    segments a length that the toxic dictionary takes at least. part: bytes of
    a dictionary's own part and of its common part. miss_cost: what a
    missed toxic text weighs against a false alarm; shifts the calibration."""

    per_class: int = 1500
    window: int = 64
    lengths: tuple[int, ...] = (5, 7, 9, 12)
    segments: int = 200
    significance: float = 6.0
    fill: int = 25
    part: int = 6000
    level: int = 5
    miss_cost: float = 2.0


@dataclass(frozen=True)
class Model:
    toxic: bytes
    ordinary: bytes
    window: int
    level: int
    weights: list[float] = field(default_factory=list)
    mean: list[float] = field(default_factory=list)
    scale: list[float] = field(default_factory=list)
    prior: float = 0.0


def fold(text: str | None) -> bytes:
    return b" " + b" ".join((text or "").encode("utf-8").lower().split()) + b" "


def _grams(b: bytes, n: int):
    import numpy as np

    a = np.frombuffer(b, np.uint8).astype(np.uint64)
    if len(a) < n:
        return np.zeros(0, np.uint64)
    h = np.zeros(len(a) - n + 1, np.uint64)
    for j in range(n):
        h = h * np.uint64(0x9E3779B97F4A7C15) + a[j : len(a) - n + 1 + j] + np.uint64(1)
    return h


def _sum_by_key(keys, *cols):
    import numpy as np

    u, at = np.unique(keys, return_inverse=True)
    return [u, *(np.bincount(at, c, len(u)).astype(np.float32) for c in cols)]


def _usage(texts: list[bytes], n: int, most: int = 4):
    """Per segment of n bytes: sum and sum of squares of its count in a text."""
    import numpy as np

    held = [np.zeros(0, np.uint64), np.zeros(0, np.float32), np.zeros(0, np.float32)]
    for i in range(0, len(texts), 100):
        parts = [np.unique(_grams(b, n), return_counts=True) for b in texts[i : i + 100]]
        k = np.concatenate([np.minimum(c, most) for _, c in parts]).astype(np.float32)
        new = _sum_by_key(np.concatenate([u for u, _ in parts]), k, k * k)
        held = _sum_by_key(*(np.concatenate(x) for x in zip(held, new, strict=True)))
    return held


def _usage_of(keys, texts: list[bytes], n: int, most: int = 4):
    """The same for given sorted keys alone."""
    import numpy as np

    s, q = np.zeros(len(keys)), np.zeros(len(keys))
    for b in texts:
        u, c = np.unique(_grams(b, n), return_counts=True)
        at = np.searchsorted(keys, u)
        at[at == len(keys)] = 0
        hit = keys[at] == u
        k = np.minimum(c[hit], most)
        s[at[hit]] += k
        q[at[hit]] += k * k
    return s, q


def _typical(of: list[bytes], against: list[bytes], s: Settings, fill: int = 0) -> list[bytes]:
    """Segments that texts of one class use more, the surest last; ``fill`` of
    each length even where they are not significant."""
    import numpy as np

    found: dict[bytes, float] = {}
    for n in s.lengths:
        ka, sa, qa = _usage(of, n)
        often = sa >= (3 if fill else 5)
        ka, sa, qa = ka[often], sa[often].astype(float), qa[often].astype(float)
        if not len(ka) or not against:
            continue
        sb, qb = _usage_of(ka, against, n)
        ma, mb = sa / len(of), sb / len(against)
        va, vb = qa / len(of) - ma**2, qb / len(against) - mb**2
        z = (ma - mb) / np.sqrt(va / len(of) + np.maximum(vb, 1 / len(against)) / len(against) + 1e-9)
        z[ma < 2 * mb] = 0
        best = np.argsort(-z, kind="stable")[: s.segments]
        best = best[: max(fill, int((z[best] > s.significance).sum()))]
        best = best[z[best] > 0]
        want = dict(zip(ka[best].tolist(), z[best].tolist(), strict=True))
        keys = np.array(sorted(want), np.uint64)
        for b in of:
            h = _grams(b, n)
            for p in np.flatnonzero(np.isin(h, keys)).tolist():
                found.setdefault(b[p : p + n], want[int(h[p])])
    return [g for g, _ in sorted(found.items(), key=lambda kv: (kv[1], kv[0]))]


def _dictionary(own: list[bytes], common: bytes, part: int) -> bytes:
    return b"".join(own)[-part:].rjust(part, b"\0") + common


def _lengths(content: bytes, level: int, data: bytes, segments: bytes, n: int):
    """Compressed length of each of n windows of data."""
    import numpy as np
    import zstandard

    d = zstandard.ZstdCompressionDict(content, dict_type=zstandard.DICT_TYPE_RAWCONTENT)
    d.precompute_compress(level=level)
    c = zstandard.ZstdCompressor(level=level, dict_data=d, write_content_size=False, write_checksum=False, write_dict_id=False)
    out = c.multi_compress_to_buffer(zstandard.BufferWithSegments(data, segments), threads=0)
    return np.fromiter((len(out[i]) for i in range(n)), np.int64, n)


def features(m: Model, texts: list[bytes]):
    """How the windows of each text compress under the two dictionaries."""
    import numpy as np

    if not texts:
        return np.zeros((0, 10))
    size = np.array([len(b) for b in texts])
    count = np.maximum(1, -(-size // m.window))
    base = np.repeat(np.cumsum(size) - size, count)
    first = np.cumsum(count) - count
    inside = (np.arange(count.sum()) - np.repeat(first, count)) * m.window
    width = np.minimum(m.window, np.repeat(size, count) - inside)
    segments = np.stack([base + inside, width], 1).astype("<u8").tobytes()
    data = b"".join(texts)
    gain = _lengths(m.ordinary, m.level, data, segments, len(base)) - _lengths(m.toxic, m.level, data, segments, len(base))
    rows = np.zeros((len(texts), 10))
    for i, (o, k) in enumerate(zip(first.tolist(), count.tolist(), strict=True)):
        v = gain[o : o + k]
        top = np.sort(v)[::-1][:6] if k <= 64 else np.sort(np.partition(v, k - 6)[-6:])[::-1]
        over = [int((v >= x).sum()) for x in (2, 4, 6)]
        rows[i] = (min(top[0], 8), top[:3].mean(), top.mean(), v.mean(), over[0] / k, over[1] / k, over[2] / k, np.log1p(over[1]), np.log1p(over[0]), np.log(k))
    return rows


def _calibrate(x, y) -> tuple[list[float], list[float], list[float]]:
    """Ridge logistic regression by Newton steps on standardised columns."""
    import numpy as np

    mean, scale = x.mean(0), x.std(0) + 1e-9
    z = np.c_[(x - mean) / scale, np.ones(len(x))]
    w = np.zeros(z.shape[1])
    ridge = np.eye(len(w))
    ridge[-1, -1] = 1e-6
    for _ in range(40):
        p = 1 / (1 + np.exp(-np.clip(z @ w, -30, 30)))
        w -= np.linalg.solve(z.T @ (z * (p * (1 - p))[:, None]) + ridge, z.T @ (p - y) + ridge @ w)
    return w.tolist(), mean.tolist(), scale.tolist()


def probabilities(m: Model, x):
    import numpy as np

    if not m.weights:
        return np.full(len(x), m.prior)
    z = np.c_[(x - np.array(m.mean)) / np.array(m.scale), np.ones(len(x))] @ np.array(m.weights)
    return 1 / (1 + np.exp(-np.clip(z, -30, 30)))


def fit(toxic: list[str], ordinary: list[str], rate: float | None = None, s: Settings | None = None) -> Model:
    """Train both dictionaries on two thirds of each class, calibrate on the rest.

    rate: share of toxic texts among all, to which the calibration is shifted
    as classes are sampled unevenly. With a class of under three texts there
    is nothing to compare: the score is then the rate itself.
    """
    import numpy as np

    s = s or Settings()
    n1, n0 = len(toxic), len(ordinary)
    rate = n1 / max(1, n1 + n0) if rate is None else rate
    if min(n1, n0) < 3:
        return Model(b"", b"", s.window, s.level, prior=rate)
    t, o = [fold(x) for x in toxic], [fold(x) for x in ordinary]
    t_in, o_in = t[: n1 * 2 // 3], o[: n0 * 2 // 3]
    words: dict[bytes, int] = {}
    for b in o_in:
        for w in set(b.split()):
            words[w] = words.get(w, 0) + 1
    common = b" ".join(sorted(words, key=lambda w: (words[w], w)))[-s.part :]
    m = Model(_dictionary(_typical(t_in, o_in, s, s.fill), common, s.part), _dictionary(_typical(o_in, t_in, s), common, s.part), s.window, s.level)
    x = features(m, [*t[len(t_in) :], *o[len(o_in) :]])
    y = np.array([1] * (n1 - len(t_in)) + [0] * (n0 - len(o_in)), float)
    w, mean, scale = _calibrate(x, y)
    sampled, rate = y.mean(), min(max(rate, 1e-4), 1 - 1e-4)
    w[-1] += float(np.log(rate / (1 - rate)) - np.log(sampled / (1 - sampled)) + np.log(s.miss_cost))
    return Model(m.toxic, m.ordinary, s.window, s.level, w, mean, scale, rate)


def train(docs: DataFrame, labels: DataFrame, folds: int | None = 5, s: Settings | None = None) -> Model:
    """Fit on a bounded sample of labelled texts: of each class the
    ``per_class`` ids of least hash. ``folds`` leaves out ids whose crc32 it
    divides. Null labels and ids are skipped; an id labelled twice is toxic if
    one label says so; of rows that repeat an id the least text is learnt from;
    null texts are empty; without a document or a label the score is 0."""
    s = s or Settings()
    known = labels.filter(F.col("doc_id").isNotNull() & F.col("toxic").isNotNull()).groupBy("doc_id").agg(F.max("toxic").alias("y"))
    if folds:
        known = known.filter(~held_out(F.col("doc_id"), folds))
    share = known.agg(F.avg((F.col("y") > 0).cast("double"))).first()[0]
    rank = [F.xxhash64("doc_id"), F.col("doc_id")]
    sample = known.filter("y > 0").orderBy(*rank).limit(s.per_class).unionByName(known.filter("y <= 0").orderBy(*rank).limit(s.per_class))
    texts = docs.select("doc_id", text_or_empty("text").alias("text"))
    chosen = texts.join(F.broadcast(sample), "doc_id").groupBy("doc_id").agg(F.min("y").alias("y"), F.min("text").alias("text"))
    rows = chosen.select("y", "text", F.xxhash64("doc_id").alias("r")).collect()  # 2 * per_class texts at most
    rows.sort(key=lambda r: (r.r, r.text))
    return fit([r.text for r in rows if r.y > 0], [r.text for r in rows if r.y <= 0], share or 0.0, s)


def score(docs: DataFrame, model: Model, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(id, score double): one row per row of ``docs``, read whole; null texts
    are empty; other columns are not read."""
    kind = docs.schema[id_col].dataType.simpleString()
    sent = docs.sparkSession.sparkContext.broadcast(model)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        m = sent.value
        for b in blocks(batches, "text"):
            x = features(m, [fold(t) for t in b.column("text").to_pylist()]) if m.weights else [0] * b.num_rows
            yield pa.RecordBatch.from_arrays([b.column("id"), pa.array(probabilities(m, x))], ["id", "score"])

    return docs.select(F.col(id_col).alias("id"), text_or_empty(text_col).alias("text")).mapInArrow(run, f"id {kind}, score double")


def without_toxic(docs: DataFrame, model: Model, threshold: float = 0.5) -> DataFrame:
    """Rows of ``docs``, all columns, whose score stays under the threshold.

    Each row is judged by its own text, null as empty: repeated rows stay or
    go together, ids are not read, an empty table gives an empty one."""
    sent = docs.sparkSession.sparkContext.broadcast(model)

    def make():
        m = sent.value
        return lambda texts: (probabilities(m, features(m, [fold(t) for t in texts]) if m.weights else [0] * len(texts)) < threshold).tolist()

    return keep_rows(docs, make)
