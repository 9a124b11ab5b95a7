"""Class-based bigram language model with Brown classes by exchange.

p(word | word before) = p(class | class before) * p(word | class).

Counts of words cover every training text. Frequent words are clustered one by
one, the others in groups of equal last three bytes, so each word, seen or not,
has a class that a task can tell from a table of fixed size. The exchange runs
in passes: all cores count how each unit's neighbours fall into the present
classes, and the driver moves units between classes by the exact gain in class
bigram likelihood on those counts. Emissions use the counts of single words,
also of rare ones; those are looked up by a join, not from a table in memory.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass
from typing import Any

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from edgeconn.llm.common import blocks, text_or_empty
from edgeconn.plans.staging import Staged, stage

ALPHA = 0.1


@dataclass(frozen=True)
class Settings:
    """classes: besides the end's own. single: words clustered one by one.
    groups: of the other words. table: words whose counts each task holds; the
    rest are joined (results do not depend on it). passes: of the exchange.
    back: weight of the class unigram in a transition."""

    classes: int = 48
    single: int = 8192
    groups: int = 2048
    table: int = 1 << 17
    passes: int = 5
    back: float = 10.0

    @property
    def units(self) -> int:
        return self.single + self.groups + 1

    @property
    def end(self) -> int:
        return self.single + self.groups


def group_of(word: bytes, groups: int) -> int:
    from zlib import crc32

    return crc32(word[-3:]) % groups


def tokens(text: pa.Array):
    """(distinct words, code of each token, tokens per text), words alone."""
    import numpy as np
    import pyarrow.compute as pc

    lists = pc.ascii_split_whitespace(pc.ascii_lower(text))
    words, ends = lists.flatten(), lists.offsets.to_numpy()[1:] - lists.offsets.to_numpy()[0]
    full = pc.greater(pc.binary_length(words), 0)
    kept = np.r_[0, np.cumsum(full.to_numpy(zero_copy_only=False))]
    coded = pc.dictionary_encode(words.filter(full))
    if isinstance(coded, pa.ChunkedArray):
        coded = coded.combine_chunks()
    return coded.dictionary, coded.indices.to_numpy(), np.diff(np.r_[0, kept[ends]])


def word_counts(texts: DataFrame) -> DataFrame:
    """(word, c): how often each word occurs in the column ``text``."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        import numpy as np

        for b in blocks(batches, "text", 16 << 20):
            words, codes, _ = tokens(b.column("text"))
            yield pa.RecordBatch.from_arrays([words, pa.array(np.bincount(codes, minlength=len(words)), pa.int64())], ["word", "c"])

    return texts.mapInArrow(run, "word string, c long").groupBy("word").agg(F.sum("c").alias("c"))


def _units(words: pa.Array, head: pa.Array, s: Settings):
    """(unit, place in the head table or -1) of each distinct word."""
    import numpy as np
    import pyarrow.compute as pc

    at = pc.fill_null(pc.index_in(words, value_set=head), -1).to_numpy(zero_copy_only=False).astype(np.int64)
    unit = at.copy()
    rest = np.flatnonzero((at < 0) | (at >= s.single))
    unit[rest] = [s.single + group_of(w.encode(), s.groups) for w in words.take(pa.array(rest)).to_pylist()]
    return unit, at


def _with_ends(codes, sizes, end: int):
    """Token codes with an end after each text."""
    import numpy as np

    return np.insert(codes, np.cumsum(sizes), end)


def _encode(texts: DataFrame, head, s: Settings) -> DataFrame:
    """(ids binary): the unit of every token of many texts, two bytes each."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        import numpy as np

        names = head.value
        for b in blocks(batches, "text", 8 << 20):
            words, codes, sizes = tokens(b.column("text"))
            unit, _ = _units(words, names, s)
            ids = _with_ends(unit[codes], sizes, s.end).astype(np.uint16)
            yield pa.RecordBatch.from_arrays([pa.array([ids.tobytes()], pa.binary())], ["ids"])

    return texts.mapInArrow(run, "ids binary")


def _neighbours(encoded: DataFrame, classes, s: Settings):
    """(right, left): of each unit, how many tokens of each class follow and
    precede it. Summed by cell across the cluster; 2 * units * classes cells
    at most come to the driver."""
    import numpy as np

    k, u = s.classes + 1, s.units
    sent = encoded.sparkSession.sparkContext.broadcast(classes.astype(np.int64))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        cls, total = sent.value, np.zeros(2 * u * k, np.int64)
        for b in batches:
            for blob in b.column("ids"):
                ids = np.frombuffer(blob.as_buffer(), np.uint16).astype(np.int64)
                if not len(ids):
                    continue
                before = np.r_[np.int64(s.end), ids[:-1]]  # a text starts after an end
                total[: u * k] += np.bincount(before * k + cls[ids], minlength=u * k)
                total[u * k :] += np.bincount(ids * k + cls[before], minlength=u * k)
        cell = np.flatnonzero(total)
        if len(cell):
            yield pa.RecordBatch.from_arrays([pa.array(cell), pa.array(total[cell])], ["cell", "n"])

    cells = encoded.mapInArrow(run, "cell long, n long").groupBy("cell").agg(F.sum("n").alias("n")).toArrow()
    out = np.zeros(2 * u * k)
    out[cells.column("cell").to_numpy()] = cells.column("n").to_numpy()
    return out[: u * k].reshape(u, k), out[u * k :].reshape(u, k)


def _xlogx(v):
    import numpy as np

    return v * np.log(np.maximum(v, 1e-300))


def likelihood(pairs) -> float:
    """Class bigram log likelihood of the counts, without the word terms."""
    return float(_xlogx(pairs).sum() - _xlogx(pairs.sum(0)).sum() - _xlogx(pairs.sum(1)).sum())


def exchange(right, left, classes, fixed: int):
    """One sweep over all units but ``fixed``, most frequent first: each goes
    to the class where the likelihood on the given counts is greatest."""
    import numpy as np

    cls, k = classes.copy(), right.shape[1]
    pairs = np.zeros((k, k))
    np.add.at(pairs, cls, right)
    out, inn = pairs.sum(1), pairs.sum(0)
    weight = right.sum(1)
    own = cls[fixed]
    for u in np.argsort(-weight, kind="stable").tolist():
        if u == fixed or not weight[u]:
            continue
        c, r, l = cls[u], right[u], left[u]
        pairs[c] -= r
        pairs[:, c] -= l
        n_out, n_in = r.sum(), l.sum()
        out[c] -= n_out
        inn[c] -= n_in
        np.maximum(pairs, 0, out=pairs)
        b, a = np.flatnonzero(r), np.flatnonzero(l)
        gain = (_xlogx(pairs[:, b] + r[b]) - _xlogx(pairs[:, b])).sum(1) + (_xlogx(pairs[a].T + l[a]) - _xlogx(pairs[a].T)).sum(1)
        gain -= _xlogx(np.maximum(out, 0) + n_out) - _xlogx(np.maximum(out, 0)) + _xlogx(np.maximum(inn, 0) + n_in) - _xlogx(np.maximum(inn, 0))
        gain[own] = -np.inf
        d = int(np.argmax(gain))
        if gain[d] <= gain[c] + 1e-9:
            d = c
        cls[u] = d
        pairs[d] += r
        pairs[:, d] += l
        out[d] += n_out
        inn[d] += n_in
    return cls


@dataclass(frozen=True)
class Model:
    """The fitted model; counts of words outside ``head`` stay in ``vocab``."""

    settings: Settings
    vocab: Staged
    head: Any  # words of the count table, by falling count
    head_count: Any
    n: int
    v: int
    ends: int
    classes: Any  # of units
    step: Any  # log10 p(class | class before)
    room: Any  # log10 of an emission's denominator
    trace: list[float]


def train(texts: DataFrame, s: Settings | None = None) -> Model:
    """Fit on every row of the column ``text``; null texts are empty, and each
    text counts an end. Without any row all words are unseen."""
    import numpy as np

    s = s or Settings()
    spark: SparkSession = texts.sparkSession
    texts = texts.select(text_or_empty("text").alias("text"))
    vocab = stage(word_counts(texts), "lm-vocab")
    ends = texts.count()
    row = vocab.df.agg(F.coalesce(F.sum("c"), F.lit(0)), F.count(F.lit(1))).first()
    n, v = row[0] + ends, row[1] + bool(ends)
    top = vocab.df.orderBy(F.desc("c"), "word").limit(s.table).toArrow()  # of fixed size
    head, head_count = top.column("word").combine_chunks(), top.column("c").to_numpy()

    encoded = stage(_encode(texts, spark.sparkContext.broadcast(head), s), "lm-units")
    k = s.classes + 1
    classes = np.arange(s.units) % s.classes
    classes[s.end] = s.classes
    best, trace = None, []
    for _ in range(s.passes + 1):
        right, left = _neighbours(encoded.df, classes, s)
        pairs = np.zeros((k, k))
        np.add.at(pairs, classes, right)
        trace.append(likelihood(pairs))
        if best is None or trace[-1] > best[0]:
            best = trace[-1], classes, pairs
        if len(trace) > 1 and trace[-1] - trace[-2] < 1e-4 * abs(trace[-2]):
            break
        classes = exchange(right, left, classes, s.end)
    encoded.drop()
    _, classes, pairs = best

    # Tokens and distinct words of each class.
    kinds, size = np.zeros(k), np.zeros(k)
    np.add.at(size, classes[: min(s.single, len(head))], head_count[: s.single])
    np.add.at(kinds, classes[: min(s.single, len(head))], 1)
    single = pa.array(head[: s.single])
    for g, c, m in _group_sizes(vocab.df, spark.sparkContext.broadcast(single), s):
        size[classes[s.single + g]] += c
        kinds[classes[s.single + g]] += m
    size[s.classes], kinds[s.classes] = ends, bool(ends)
    uni = (size + 1) / (size.sum() + k)
    step = np.log10((pairs + s.back * uni) / (pairs.sum(1, keepdims=True) + s.back))
    return Model(s, vocab, head, head_count, int(n), int(v), ends, classes, step, np.log10(size + ALPHA * (kinds + 1)), trace)


def _group_sizes(vocab: DataFrame, single, s: Settings) -> list:
    """(group, tokens, distinct words) of words that are not single."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        import numpy as np

        for b in batches:
            unit, _ = _units(b.column("word"), single.value, s)
            g = unit - s.single
            mine = g >= 0
            c = np.bincount(g[mine], b.column("c").to_numpy()[mine], s.groups)
            m = np.bincount(g[mine], minlength=s.groups)
            at = np.flatnonzero(m)
            yield pa.RecordBatch.from_arrays([pa.array(at), pa.array(c[at].astype(np.int64)), pa.array(m[at])], ["g", "c", "m"])

    return [tuple(r) for r in vocab.mapInArrow(run, "g long, c long, m long").groupBy("g").agg(F.sum("c"), F.sum("m")).collect()]  # groups rows


def score(docs: DataFrame, model: Model, keys: list[str]) -> DataFrame:
    """(*keys, n_tokens, n_known, train_tokens, base_score, score), one row per
    row of ``docs`` (columns keys and text); log10 probabilities, the end's
    included. Null texts are empty: one end. Repeated rows stay."""
    s = model.settings
    sc = docs.sparkSession.sparkContext
    end_value = float(model.ends)
    sent = sc.broadcast((model.head, model.head_count, model.classes, model.step, model.room))
    base_room = model.n + ALPHA * (model.v + 1)
    kept = [f for f in docs.schema.fields if f.name in keys]
    schema = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in kept) + ", row_no long, n_tokens long, n_known long, seen double, fitted double, rare array<struct<word:string,n:long>>"

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        import numpy as np
        from pyspark import TaskContext

        head, head_count, classes, step, room = sent.value
        log_head = np.log10(head_count + ALPHA) if len(head) else np.zeros(0)
        row = TaskContext.get().partitionId() << 40
        rare_type = pa.list_(pa.struct([("word", pa.string()), ("n", pa.int64())]))
        for b in blocks(batches, "text", 8 << 20):
            words, codes, sizes = tokens(b.column("text"))
            unit, at = _units(words, head, s)
            n = len(words)
            unit, value = np.r_[unit, s.end], np.r_[np.where(at >= 0, log_head[np.maximum(at, 0)] if len(head) else 0.0, 0.0), np.log10(end_value + ALPHA)]
            in_table = np.r_[at >= 0, True]
            codes = _with_ends(codes, sizes, n)
            first = np.cumsum(sizes + 1) - sizes - 1
            cls = classes[unit][codes]
            before = np.r_[np.int64(s.classes), cls[:-1]]
            seen = np.add.reduceat(value[codes], first)
            fitted = np.add.reduceat(step[before, cls] - room[cls], first)
            known = np.add.reduceat((in_table[codes] & ~((codes == n) & (end_value == 0))).astype(np.int64), first)
            doc = np.repeat(np.arange(len(sizes)), sizes + 1)
            out = ~in_table[codes]
            pair, many = np.unique(doc[out] * np.int64(n + 1) + codes[out], return_counts=True)
            rare = pa.StructArray.from_arrays([words.take(pa.array(pair % (n + 1))).cast(pa.string()), pa.array(many, pa.int64())], ["word", "n"])
            offsets = np.searchsorted(pair // (n + 1), np.arange(len(sizes) + 1))
            lists = pa.ListArray.from_arrays(pa.array(offsets, pa.int32()), rare).cast(rare_type)
            rows = np.arange(row, row + len(sizes))
            row += len(sizes)
            yield pa.RecordBatch.from_arrays([*(b.column(f.name) for f in kept), pa.array(rows), pa.array(sizes + 1, pa.int64()), pa.array(known), pa.array(seen), pa.array(fitted), lists], [*(f.name for f in kept), "row_no", "n_tokens", "n_known", "seen", "fitted", "rare"])

    held = stage(docs.select(*keys, text_or_empty("text").alias("text")).mapInArrow(run, schema), "lm-scores").df
    rare = held.select("row_no", F.explode("rare").alias("r")).select("row_no", "r.word", "r.n")
    counts = model.vocab.df
    found = rare.join(counts, "word", "left").groupBy("row_no").agg(
        F.sum(F.col("n") * F.log10(F.coalesce("c", F.lit(0)) + ALPHA)).alias("more"), F.sum(F.when(F.col("c") > 0, F.col("n")).otherwise(0)).alias("also")
    )
    whole = held.drop("rare").join(found, "row_no", "left")
    seen = F.col("seen") + F.coalesce("more", F.lit(0.0))
    import math

    return whole.select(
        *keys, "n_tokens", (F.col("n_known") + F.coalesce("also", F.lit(0))).alias("n_known"), F.lit(model.n).cast("long").alias("train_tokens"),
        (seen - F.col("n_tokens") * math.log10(base_room)).alias("base_score"), (seen + F.col("fitted")).alias("score"),
    )
