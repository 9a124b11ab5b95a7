"""SimHash near-duplicates through deletion-variant signatures.

Fingerprints are cut into few, long segments. Where two fingerprints differ in
at most ``2 * segments - 1`` bits, one segment differs in at most one, so the
two share that segment with one bit struck out. Each distinct fingerprint is
indexed under every (segment, struck bit) variant; equal variants meet by an
equality shuffle of 16-byte rows, and what meets is verified on all bits.

Inside a variant's bucket the links are found by a search that takes every
fingerprint off the list once it is reached: it emits a spanning forest of the
bucket's link graph, so a bucket of m close copies makes m - 1 rows, not m**2,
and no link between different texts is lost for the components. Buckets over
``HOT`` rows are dealt anew by variants of the remaining bits.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from edgeconn.llm.common import blocks, text_or_empty
from edgeconn.operators.components import star_components
from edgeconn.plans.staging import stage

HOT = 1 << 14


@dataclass(frozen=True)
class SimHash:
    """Parameters of a SimHash index.

    bits: width, a multiple of 64. segments: pieces of the fingerprint, each at
    most 48 bits. max_bits: fingerprints link at so many differing bits; the
    search is exact while max_bits < 2 * segments, beyond that a pair is found
    if any one segment differs in at most one bit. words: shingle length.
    distinct: count a shingle once per text.
    """

    bits: int = 64
    segments: int = 2
    max_bits: int = 3
    words: int = 3
    distinct: bool = False

    @property
    def size(self) -> int:
        """Bytes of a fingerprint."""
        return self.bits // 8

    def cuts(self) -> list[tuple[int, int]]:
        at = [self.bits * i // self.segments for i in range(self.segments + 1)]
        return list(zip(at, at[1:], strict=False))


def text_fingerprint(text: str | None, p: SimHash) -> bytes:
    """Big-endian fingerprint of one whole text; zero where it has no word."""
    words = (text or "").encode("utf-8").lower().split()
    if not words:
        return bytes(p.size)
    return _lanes(words, p.words, p.bits // 64, p.distinct)


def _lanes(words: list[bytes], k: int, lanes: int, distinct: bool) -> bytes:
    """64 majority bits for each lane of hashes of the k-word shingles."""
    import numpy as np
    import xxhash

    if len(words) < k:
        shingles = [b" ".join(words)]
    else:
        shingles = list(map(b" ".join, zip(*(words[i:] for i in range(k)), strict=False)))
    digest = xxhash.xxh64_intdigest
    if distinct:
        shingles = list(set(shingles))
    h = np.fromiter([digest(s, 42) for s in shingles], np.uint64, len(shingles))
    out = []
    for lane in range(lanes):
        v = h
        if lane:  # further lanes by a published 64-bit finalizer of the same hash
            h = h + np.uint64(0x9E3779B97F4A7C15)
            z = (h ^ (h >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
            z = (z ^ (z >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
            v = z ^ (z >> np.uint64(31))
        ones = np.zeros(64, np.int64)
        for i in range(0, len(v), 1 << 16):
            part = v[i : i + (1 << 16)].astype(">u8").view(np.uint8).reshape(-1, 8)
            ones += np.unpackbits(part, axis=1).sum(0, dtype=np.int64)
        out.append(np.packbits(2 * ones > len(v)).tobytes())
    return b"".join(out)


def fingerprints(docs: DataFrame, p: SimHash, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(id, fp binary): one row per row of ``docs``; a null text is empty."""
    kind = docs.schema[id_col].dataType.simpleString()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in blocks(batches, "text"):
            fp = [text_fingerprint(t, p) for t in b.column("text").to_pylist()]
            yield pa.RecordBatch.from_arrays([b.column("id"), pa.array(fp, pa.binary())], ["id", "fp"])

    return docs.select(F.col(id_col).alias("id"), text_or_empty(text_col).alias("text")).mapInArrow(run, f"id {kind}, fp binary")


def _as_words(col: pa.Array, width: int):
    """Fingerprints of a binary column as rows of bytes."""
    import numpy as np

    return np.frombuffer(b"".join(col.to_pylist()), np.uint8).reshape(-1, width)


def _strike(bits, first: int, width: int, tag0: int):
    """Keys of every row's bits [first, first + width) with one bit struck out."""
    import numpy as np

    seg = bits[:, first : first + width].astype(np.uint64) @ (np.uint64(1) << np.arange(width, dtype=np.uint64))
    masks = ~(np.uint64(1) << np.arange(width, dtype=np.uint64))
    tags = (np.uint64(tag0) + np.arange(width, dtype=np.uint64)) << np.uint64(48)
    return (seg[:, None] & masks) | tags


def variant_keys(distinct: DataFrame, p: SimHash) -> DataFrame:
    """(key, ref): bits x one row per distinct fingerprint; ref = hash of fp.

    Rows are 16 bytes, so the equality shuffle carries no fingerprint. Equal
    refs of different fingerprints only add candidates.
    """
    if any(b - a > 48 for a, b in p.cuts()):
        raise ValueError("a segment has at most 48 bits")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        import numpy as np

        for b in batches:
            for i in range(0, b.num_rows, 1024):
                part = b.slice(i, 1024)
                bits = np.unpackbits(_as_words(part.column("fp"), p.size), axis=1)
                keys = np.concatenate([_strike(bits, a, z - a, a) for a, z in p.cuts()], axis=1)
                ref = np.repeat(part.column("ref").to_numpy(), keys.shape[1])
                yield pa.RecordBatch.from_arrays([pa.array(keys.ravel().view(np.int64)), pa.array(ref)], ["key", "ref"])

    return distinct.select("fp", F.xxhash64("fp").alias("ref")).mapInArrow(run, "key long, ref long")


def _runs(batches: Iterator[pa.RecordBatch], names: list[str]):
    """Whole runs of equal key: yields tables in which no key is cut."""
    import numpy as np

    held: list[pa.RecordBatch] = []
    for b in batches:
        if not b.num_rows:
            continue
        key = b.column("key").to_numpy()
        last = int(np.searchsorted(key, key[-1], "left"))
        if last == 0 and held and held[-1].column("key")[0].as_py() == key[0]:
            held.append(b)
            continue
        head = pa.Table.from_batches([*held, b.slice(0, last)], b.schema)
        if head.num_rows:
            yield head.select(names).combine_chunks()
        held = [b.slice(last)]
    if held:
        yield pa.Table.from_batches(held).select(names).combine_chunks()


def _shared(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Rows of sorted input whose key has at least two rows."""
    import numpy as np

    tail = None  # last row of the batch before, and whether it was given out
    for b in batches:
        if not b.num_rows:
            continue
        key, ref = b.column("key").to_numpy(), b.column("ref").to_numpy()
        same = key[1:] == key[:-1]
        keep = np.zeros(len(key), bool)
        keep[1:] |= same
        keep[:-1] |= same
        if tail is not None and tail[0] == key[0]:
            keep[0] = True
            if not tail[2]:
                yield pa.RecordBatch.from_arrays([pa.array([tail[0]], pa.int64()), pa.array([tail[1]], pa.int64())], ["key", "ref"])
        if keep.any():
            yield pa.RecordBatch.from_arrays([pa.array(key[keep]), pa.array(ref[keep])], ["key", "ref"])
        tail = (int(key[-1]), int(ref[-1]), bool(keep[-1]))


def spanning_links(words, max_bits: int) -> list[tuple[int, int]]:
    """A spanning forest of the graph that joins rows within ``max_bits``."""
    import numpy as np

    left, out = np.arange(len(words)), []
    while len(left) > 1:
        front, left = [int(left[0])], left[1:]
        while front and len(left):
            at = front.pop()
            near = np.bitwise_count(words[left] ^ words[at]).sum(1, dtype=np.int64) <= max_bits
            if near.any():
                hit = left[near].tolist()
                out += [(at, x) for x in hit]
                front += hit
                left = left[~near]
    return out


def _bucket_links(p: SimHash):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        import numpy as np

        for t in _runs(batches, ["key", "fp"]):
            key = t.column("key").to_numpy()
            fps = t.column("fp").combine_chunks() if isinstance(t.column("fp"), pa.ChunkedArray) else t.column("fp")
            words = np.ascontiguousarray(_as_words(fps, p.size)).view(np.uint64)
            start = np.flatnonzero(np.r_[True, key[1:] != key[:-1]])
            size = np.diff(np.r_[start, len(key)])
            two = start[size == 2]
            close = np.bitwise_count(words[two] ^ words[two + 1]).sum(1, dtype=np.int64) <= p.max_bits
            a, b = [two[close]], [two[close] + 1]
            for s, n in zip(start[size > 2].tolist(), size[size > 2].tolist(), strict=True):
                if found := spanning_links(words[s : s + n], p.max_bits):
                    pair = np.array(found) + s
                    a.append(pair[:, 0])
                    b.append(pair[:, 1])
            a, b = np.concatenate(a), np.concatenate(b)
            if len(a):
                yield pa.RecordBatch.from_arrays([fps.take(pa.array(a)), fps.take(pa.array(b))], ["a", "b"]).cast(pa.schema([("a", pa.binary()), ("b", pa.binary())]))

    return run


def _rekey_hot(p: SimHash):
    """Deal a hot bucket by struck-out pieces of the bits outside its segment.

    Those bits differ in at most max_bits places, so of max_bits // 2 + 1
    pieces one differs in at most one bit: no link is lost.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        import numpy as np
        import xxhash

        mix = lambda a, b: xxhash.xxh64_intdigest(int(a).to_bytes(8, "little") + int(b).to_bytes(8, "little"))
        cuts = p.cuts()
        pieces = p.max_bits // 2 + 1
        for b in batches:
            for i in range(0, b.num_rows, 1024):
                part = b.slice(i, 1024)
                bits = np.unpackbits(_as_words(part.column("fp"), p.size), axis=1)
                old, fps = part.column("key").to_numpy().view(np.uint64), part.column("fp")
                struck = (old >> np.uint64(48)).astype(np.int64)
                for a, z in cuts:
                    rows = np.flatnonzero((struck >= a) & (struck < z))
                    if not len(rows):
                        continue
                    rest = np.delete(bits[rows], np.s_[a:z], axis=1)
                    at = [rest.shape[1] * j // pieces for j in range(pieces + 1)]
                    keys = np.concatenate([_strike(rest, x, y - x, x) for x, y in zip(at, at[1:], strict=False)], axis=1)
                    new = np.array([mix(o, k) for o, row in zip(old[rows], keys, strict=True) for k in row], np.uint64).view(np.int64)
                    yield pa.RecordBatch.from_arrays([pa.array(new), fps.take(pa.array(np.repeat(rows, keys.shape[1])))], ["key", "fp"])

    return run


def links(distinct: DataFrame, p: SimHash) -> DataFrame:
    """(a, b binary): links whose components are those of all links.

    ``distinct`` has one row per different fingerprint (column fp).
    """
    sorted_keys = variant_keys(distinct, p).repartition("key").sortWithinPartitions("key")
    shared = stage(sorted_keys.mapInArrow(_shared, "key long, ref long"), "simhash-keys")
    rows = shared.df.join(distinct.select("fp", F.xxhash64("fp").alias("ref")), "ref").select("key", "fp")
    hot = shared.df.groupBy("key").count().filter(F.col("count") > HOT).select("key")
    if not hot.isEmpty():
        again = rows.join(hot, "key", "left_semi").mapInArrow(_rekey_hot(p), "key long, fp binary")
        rows = rows.join(hot, "key", "left_anti").unionByName(again)
    return rows.repartition("key").sortWithinPartitions("key", "fp").mapInArrow(_bucket_links(p), "a binary, b binary").distinct()


def near_duplicates(docs: DataFrame, p: SimHash | None = None, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(id, fp binary, component): one row per row of ``docs``.

    component is the least id that links reach, the row's own included. Null
    texts are empty; texts without a word have fingerprint zero and link like
    any other; equal texts always link. Null ids are kept, and a component of
    null ids alone is null. Repeated rows stay. Other columns of ``docs`` are
    not read, whatever their names.
    """
    p = p or SimHash()
    fps = stage(fingerprints(docs, p, id_col, text_col), "simhash-fp").df
    groups = stage(fps.groupBy("fp").agg(F.min("id").alias("first")), "simhash-groups").df
    comps = star_components(links(groups, p), "a", "b").withColumnsRenamed({"v": "fp", "comp": "root"})
    linked = stage(groups.join(comps, "fp"), "simhash-linked").df
    least = linked.groupBy("root").agg(F.min("first").alias("component"))
    of_fp = groups.join(linked.select("fp", "root").join(least, "root").select("fp", "component"), "fp", "left").select("fp", F.coalesce("component", "first").alias("component"))
    return fps.join(of_fp, "fp").select("id", "fp", "component")
