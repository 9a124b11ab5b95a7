"""Benchmark decontamination by the q-gram lemma on overlapping diagonal bands.

Benchmark items are cut into overlapping probes of normalised characters: long
ones for passages with edits, short ones for parts of an item, so that any run
of ``part + step - 1`` characters of an item holds a whole short probe. A
probe of m characters that occurs in a document with at most k edits shares at
least m + 1 - q * (k + 1) of its q-grams with the place, all on diagonals that
lie within k of each other. Shared q-grams are therefore counted in diagonal
bands that overlap by half, bands under the bound are dropped, and what is
left is verified by an alignment that stays inside the band.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from edgeconn.llm.common import blocks, keep_rows, text_or_empty
from edgeconn.plans.staging import stage

MULT = 0x9E3779B97F4A7C15
#: Bytes of text that a worker searches at once.
BLOCK = 1 << 19
#: Pairs of a gram in a text and a gram in a probe that are looked at together.
HITS = 1 << 20


@dataclass(frozen=True)
class Settings:
    """q: gram length. edits: budget as a share of a probe's length, below
    1 / q. probe, stride: probes of longer items. part, step: short probes of
    items over ``part`` characters. broadcast_chars: benchmark
    text held by a worker at once; a larger benchmark is searched for in
    several passes, each over all documents."""

    q: int = 8
    edits: float = 0.08
    probe: int = 96
    stride: int = 48
    part: int = 48
    step: int = 16
    broadcast_chars: int = 16 << 20


def normalise(text: str):
    """(code points, place in the text of each): lower case, and one blank for
    each run of what is neither letter, digit nor mark of a word."""
    import numpy as np

    low = text.lower()
    if len(low) != len(text):
        low = "".join(c if len(c.lower()) != 1 else c.lower() for c in text)
    a = np.frombuffer(low.encode("utf-32-le", "surrogatepass"), np.uint32)
    word = ((a >= 97) & (a <= 122)) | ((a >= 48) & (a <= 57)) | ((a >= 0xC0) & ((a < 0x2000) | (a > 0x206F)) & ((a < 0x3000) | (a > 0x303F)))
    keep = word.copy()
    keep[1:] |= word[:-1]
    at = np.flatnonzero(keep)
    return np.where(word[at], a[at], 32).astype(np.uint32), at


def gram_hashes(codes, q: int):
    """Hash of the q characters from each place on (by halves)."""
    import numpy as np

    n = len(codes) - q + 1
    if n <= 0:
        return np.zeros(0, np.uint64)
    h, done, bits = None, 0, q
    power, width = codes.astype(np.uint64) + np.uint64(1), 1
    factor = MULT
    while bits:
        if bits & 1:
            h = power[:n].copy() if h is None else h * np.uint64(pow(MULT, width, 1 << 64)) + power[done : done + n]
            done += width
        bits >>= 1
        if bits:
            power = power[: len(power) - width] * np.uint64(factor) + power[width:]
            width, factor = 2 * width, pow(factor, 2, 1 << 64)
    return h * np.uint64(0xD6E8FEB86659FD93)


class Probes:
    """Probes of a benchmark and the places of their q-grams."""

    def __init__(self, items: list[tuple[int, str]], s: Settings):
        import numpy as np

        self.s, self.codes, self.item, self.budget, self.short = s, [], [], [], []
        for item, text in items:
            codes, _ = normalise(text or "")
            if len(codes) and codes[-1] == 32:  # what follows the last word is the document's
                codes = codes[:-1]
            if len(codes) < s.q:
                continue
            cuts = [(False, s.probe, s.stride), *([(True, s.part, s.step)] if len(codes) > s.part else [])]
            for short, size, stride in cuts:
                last = max(0, len(codes) - size)
                starts = sorted({*range(0, last, stride), last})
                self._add(item, [codes[at : at + size] for at in starts], short)
        self.budget = np.maximum(np.array(self.budget, np.int64), 0)
        self.size = np.array([len(c) for c in self.codes], np.int64)
        self.need = np.maximum(self.size + 1 - s.q * (self.budget + 1), 1)
        grams = [gram_hashes(c, s.q) for c in self.codes]
        h = np.concatenate(grams) if grams else np.zeros(0, np.uint64)
        no = np.repeat(np.arange(len(grams)), [len(g) for g in grams])
        pos = np.concatenate([np.arange(len(g)) for g in grams]) if grams else np.zeros(0, np.int64)
        order = np.argsort(h, kind="stable")
        self.keys, self.first, self.count = np.unique(h[order], return_index=True, return_counts=True)
        self.no, self.pos = no[order], pos[order]
        self.shift = np.uint64(40)  # 2**24 places of one byte
        self.there = np.zeros(1 << 24, bool)
        self.there[(self.keys >> self.shift).astype(np.int64)] = True
        self.band = int(max(1, self.budget.max(initial=0))) + 1

    def _add(self, item: int, parts: list, short: bool) -> None:
        q = self.s.q
        for part in parts:
            self.codes.append(part)
            self.item.append(item)
            self.short.append(short)
            self.budget.append(min(int(self.s.edits * len(part)), (len(part) + 1) // q - 2) if len(part) >= 3 * q else 0)


def align(text, probe, low: int, high: int) -> tuple[int, int, int]:
    """(edits, start, end) of the best place of the probe in the text whose
    diagonals (place in the text less place in the probe) lie in [low, high].
    Row by row over the probe, all diagonals at once."""
    import numpy as np

    width, far = high - low + 1, 1 << 20
    lane = np.arange(width)
    at = low + lane
    cost = np.where((at >= 0) & (at <= len(text)), 0, far)
    start = at.copy()
    skip, moved = np.full(width, far), np.zeros(width, np.int64)
    padded = np.concatenate([text, np.array([0], text.dtype)])
    for i, c in enumerate(probe):
        here = low + lane + i  # the character that a step on this diagonal takes
        inside = (here >= 0) & (here < len(text))
        same = padded[np.clip(here, 0, len(text))] == c
        step = np.where(inside, cost + ~same, far)
        skip[:-1], moved[:-1] = cost[1:] + 1, start[1:]  # the probe's character is missing in the text
        stay = step <= skip
        new, origin = np.where(stay, step, skip), np.where(stay, start, moved)
        run = np.minimum.accumulate(new - lane)  # further characters of the text
        source = np.maximum.accumulate(np.where(new - lane == run, lane, 0))
        cost, start = run + lane, origin[source]
        ends = low + lane + i + 1
        cost = np.where((ends < 0) | (ends > len(text)), far, cost)
    best = int(np.argmin(cost))
    return int(cost[best]), int(start[best]), int(low + best + len(probe))


def find(probes: Probes, texts: list[str]) -> list[tuple[int, int, int, int, int]]:
    """(text no, probe no, start, end, edits) of each probe's places that do
    not overlap in each band that passes, in places of the original text; the
    best of a text and probe comes last."""
    import numpy as np

    s, out = probes.s, []
    if not len(probes.keys):
        return out
    parts = [normalise(t) for t in texts]
    # a wall between texts: no gram of a probe has it, and no band crosses it
    wall = np.zeros(s.q, np.uint32)
    joined = np.concatenate([x for c, _ in parts for x in (c, wall)])
    begin = np.cumsum([0, *(len(c) + s.q for c, _ in parts)])
    h = gram_hashes(joined, s.q)
    near = np.flatnonzero(probes.there[(h >> probes.shift).astype(np.int64)])
    at = np.searchsorted(probes.keys, h[near])
    at[at == len(probes.keys)] = 0
    good = probes.keys[at] == h[near]
    near, at = near[good], at[good]
    if not len(near):
        return out
    n = probes.count[at]
    w = probes.band
    cells = (int(np.diff(begin).max()) + s.probe) // w + 3
    key, hits = np.zeros(0, np.int64), np.zeros(0, np.int64)
    ends = np.cumsum(n)
    lo = 0
    while lo < len(near):  # a part of the hits at a time: repetitive texts have many a gram
        hi = max(lo + 1, int(np.searchsorted(ends, (ends[lo - 1] if lo else 0) + HITS, "right")))
        many, here = n[lo:hi], near[lo:hi]
        row = np.repeat(probes.first[at[lo:hi]], many) + np.arange(many.sum()) - np.repeat(np.cumsum(many) - many, many)
        place = np.repeat(here, many)
        doc = np.searchsorted(begin, place, "right") - 1
        cell = (place - probes.pos[row] - begin[doc] + s.probe) // w  # counted from the text's start, never negative
        new, count = np.unique((probes.no[row] * len(texts) + doc) * cells + cell, return_counts=True)
        both, where = np.unique(np.r_[key, new], return_inverse=True)
        key, hits = both, np.bincount(where, np.r_[hits, count], len(both)).astype(np.int64)
        lo = hi
    # a band is two neighbouring cells; each cell belongs to two bands
    both = hits.copy()
    follows = np.flatnonzero(np.diff(key) == 1)
    both[follows] += hits[follows + 1]
    which = key // cells
    passed = both >= probes.need[which // len(texts)]
    seen: dict[tuple[int, int], tuple[int, int]] = {}
    for k in key[passed].tolist():
        pair, c = divmod(k, cells)
        p, d = divmod(pair, len(texts))
        low = c * w - s.probe
        if (p, d) in seen and seen[p, d][1] >= low - 1:
            seen[p, d] = (seen[p, d][0], low + 2 * w - 1)
        else:
            if (p, d) in seen:
                _verify(probes, parts, d, p, *seen[p, d], out)
            seen[p, d] = (low, low + 2 * w - 1)
    for (p, d), (low, high) in seen.items():
        _verify(probes, parts, d, p, low, high, out)
    return sorted(out, key=lambda r: (r[0], r[1], -r[4]))


def _verify(probes: Probes, parts, d: int, p: int, low: int, high: int, out: list) -> None:
    codes, place = parts[d]
    k, m = int(probes.budget[p]), int(probes.size[p])
    probe = probes.codes[p]
    whole, wanted = memoryview(codes).cast("B"), probe.tobytes()
    todo = [(max(0, low - k), min(len(codes), high + m + k + 1))]
    while todo:
        a, z = todo.pop()
        if z - a < m - k:
            continue
        spans = [(a + x, a + x + m) for x in _apart(_places(bytes(whole[4 * a : 4 * z]), wanted), m)]
        if spans:  # verbatim places first; edited ones in what they leave
            out += [(d, p, int(place[x]), int(place[y - 1]) + 1, 0) for x, y in spans]
            todo += list(zip([a, *(y for _, y in spans)], [*(x for x, _ in spans), z], strict=True)) if k else []
            continue
        if not k:
            continue
        edits, start, end = align(codes[a:z], probe, low - k - a, high + k - a)
        if edits <= k and end > start:
            out.append((d, p, int(place[a + start]), int(place[a + end - 1]) + 1, edits))
            todo += [(a, a + start), (a + end, z)]


def _places(text: bytes, part: bytes):
    """Places, in code points, where a part of a text begins."""
    at = text.find(part)
    while at >= 0:
        if at % 4 == 0:
            yield at // 4
        at = text.find(part, at + 1)


def _apart(places, size: int):
    """Of rising places those that are ``size`` or more from the one before."""
    free = 0
    for x in places:
        if x >= free:
            yield x
            free = x + size


def without_repeats(probes: Probes, found: list) -> list:
    """Places of short probes go where a long probe of the item was found."""
    whole: dict[tuple, list] = {}
    for d, p, start, end, _ in found:
        if not probes.short[p]:
            whole.setdefault((d, probes.item[p]), []).append((start, end))
    inside = lambda d, p, start, end: any(a - probes.budget[p] <= start and end <= z + probes.budget[p] for a, z in whole.get((d, probes.item[p]), ()))
    return [r for r in found if not (probes.short[r[1]] and inside(*r[:4]))]


def leaks(docs: DataFrame, benchmark: DataFrame, s: Settings | None = None, id_col: str = "doc_id", item_col: str = "item_id") -> DataFrame:
    """(id, item, probe_size, start, end, edits): a row for each probe of a
    benchmark item found in a text within its edit budget; start and end are
    code points of the original text. Short probes are left out where a long
    probe of the item was found.

    Null texts are empty and hold nothing. Items without q characters, null
    ones among them, can share no q-gram and are never found; items under
    three grams long are matched without an edit. Repeated rows of either
    table stay. Other columns are not read.
    """
    s = s or Settings()
    kind = docs.schema[id_col].dataType.simpleString()
    schema = f"id {kind}, item long, probe_size int, start long, end long, edits int"
    texts = docs.select(F.col(id_col).alias("id"), text_or_empty("text").alias("text"))
    out = None
    for part, alone in _passes(benchmark, s, item_col):
        found = _search(texts, part, s, schema)
        if not alone:  # written before the next part of the benchmark is read
            found = stage(found, "leaks").df
        out = found if out is None else out.unionByName(found)
    return out


def _passes(benchmark: DataFrame, s: Settings, item_col: str) -> Iterator[tuple[list[tuple[int, str]], bool]]:
    """The items in parts of about ``broadcast_chars``, read one at a time, and
    whether there is one alone, as mostly."""
    if not s.edits < 1 / s.q:
        raise ValueError("the lemma's bound is positive only for an edit share under 1 / q")
    items = benchmark.select(F.col(item_col).cast("long").alias("item"), F.col("text").alias("text")).filter(F.col("text").isNotNull())
    chars = items.agg(F.coalesce(F.sum(F.length("text")), F.lit(0))).first()[0]
    n = max(1, -(-chars // s.broadcast_chars))
    for i in range(n):
        part = items.filter(F.pmod(F.xxhash64("item", "text"), F.lit(n)) == i).collect()
        yield sorted(((r.item, r.text) for r in part), key=lambda x: (x[0] is None, x[0] or 0, x[1])), n == 1


def without_leaks(docs: DataFrame, benchmark: DataFrame, s: Settings | None = None, item_col: str = "item_id") -> DataFrame:
    """Rows of ``docs``, all columns, in which no probe of an item is found.

    Null and empty texts hold nothing and stay; repeated rows stay or go
    together; ids are not read; without items every row stays."""
    s = s or Settings()
    for part, alone in _passes(benchmark, s, item_col):
        sent = docs.sparkSession.sparkContext.broadcast(part)

        def make(sent=sent):
            probes = Probes(sent.value, s)

            def test(texts: list[str]) -> list[bool]:
                bad = {hit[0] for hit in find(probes, texts)}
                return [i not in bad for i in range(len(texts))]

            return test

        docs = keep_rows(docs, make, limit=BLOCK)
        if not alone:
            docs = stage(docs, "without-leaks").df
    return docs


def _search(texts: DataFrame, items: list, s: Settings, schema: str) -> DataFrame:
    sent = texts.sparkSession.sparkContext.broadcast(items)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        probes = Probes(sent.value, s)
        for b in blocks(batches, "text", BLOCK):
            got = without_repeats(probes, find(probes, b.column("text").to_pylist()))
            ids = b.column("id").take(pa.array([g[0] for g in got], pa.int64()))
            cols = [[probes.item[g[1]] for g in got], [int(probes.size[g[1]]) for g in got], *([g[i] for g in got] for i in (2, 3, 4))]
            types = [pa.int64(), pa.int32(), pa.int64(), pa.int64(), pa.int32()]
            yield pa.RecordBatch.from_arrays([ids, *(pa.array(c, t) for c, t in zip(cols, types, strict=True))], ["id", "item", "probe_size", "start", "end", "edits"])

    return texts.mapInArrow(run, schema)
