"""Groups of near copies: SimHash links first, the rest by shared shingles.

Texts are near copies where the cosine of their sets of five-word shingles,
which is the similarity that SimHash bits estimate, is at least 0.8. At that
cosine a 64-bit SimHash differs in about thirteen bits, out of reach of any
index of few long segments, so the deletion variants of ``simhash`` find the
close copies alone. The pairs that they leave come from bands: a band's key
mixes the least shingle under several hashes, so two texts share it with the
share of common shingles to the power of ``rows``. Keys have 64 bits and speak
for whole texts: unrelated texts never share one by chance, and a passage that
many texts have brings none of them together.

Whatever way a pair was found, it links only where the cosine of the real sets
says so. A bucket first hands out two pairs per member; then all its pairs
whose ends the links so far leave apart are looked at. A bucket of one component
is done, whatever its size, and no pair of a mixed one is left out: its members
are dealt into blocks with their sets, and each two blocks meet in a task, so
that pairs are counted there and only links become rows.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from edgeconn.llm.common import blocks, text_or_empty
from edgeconn.llm.simhash import SimHash, _runs, links
from edgeconn.operators.components import components, star_components
from edgeconn.plans.staging import stage

MIX = 0x9E3779B97F4A7C15


@dataclass(frozen=True)
class Settings:
    """similarity: least cosine of two sets. words: of a shingle. bands, rows:
    keys of a text, and least shingles in a key; a pair with a share j of
    common shingles meets in no band with probability (1 - j**rows)**bands:
    0.01 at j = 2/3 (a cosine of 0.8 at equal sizes), 3e-6 at j = 0.8. bitmap:
    bits of the table that tells a task which texts have a candidate."""

    similarity: float = 0.8
    words: int = 5
    bands: int = 32
    rows: int = 5
    bitmap: int = 1 << 24
    simhash: SimHash = SimHash(words=5, distinct=True)


#: Texts, and bytes of their sets, of a mixed bucket that a task takes from one block.
BLOCK_ROWS, BLOCK_SETS = 2048, 8 << 20


def shingles(texts: list[str], k: int):
    """(hashes, text no): one 64-bit hash for each run of k words of each text,
    or of all its words where they are fewer; words are lower-cased (A-Z)."""
    import numpy as np
    import xxhash

    code: dict[bytes, int] = {}
    ids, sizes = [], []
    for t in texts:
        words = t.encode("utf-8", "surrogatepass").lower().split()
        sizes.append(len(words))
        ids += [code.setdefault(w, len(code)) for w in words]
    digest = np.fromiter((xxhash.xxh64_intdigest(w, 42) for w in code), np.uint64, len(code))
    sizes = np.array(sizes, np.int64)
    word = digest[np.array(ids, np.int64)] if ids else np.zeros(0, np.uint64)
    first = np.cumsum(sizes) - sizes
    n = np.where(sizes >= k, sizes - k + 1, (sizes > 0).astype(np.int64))
    no = np.repeat(np.arange(len(texts)), n)
    at = np.arange(n.sum()) - np.repeat(np.cumsum(n) - n, n) + np.repeat(first, n)
    left = np.repeat(first + sizes, n) - at  # words from here to the text's end
    h = np.zeros(len(at), np.uint64)
    for j in range(k):
        here = j < left
        h[here] = (h[here] ^ word[at[here] + j]) * np.uint64(MIX)
        h[here] ^= h[here] >> np.uint64(29)
    return _final(h), no


def _final(h):
    import numpy as np

    z = (h ^ (h >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    z = (z ^ (z >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return z ^ (z >> np.uint64(31))


def band_keys(h, first, s: Settings):
    """A row of ``bands`` keys for each run of hashes that begins at ``first``."""
    import numpy as np

    out = np.zeros((len(first), s.bands), np.uint64)
    salt = _final(np.arange(1, s.bands * s.rows + 1, dtype=np.uint64))
    for b in range(s.bands):
        key = np.full(len(first), b + 1, np.uint64)
        for r in range(s.rows):
            x = salt[b * s.rows + r]
            least = np.minimum.reduceat((h ^ x) * (x | np.uint64(1)), first)
            key = _final(key * np.uint64(MIX) + least)
        out[:, b] = key
    return out


def majority(h, first):
    """64 majority bits of each run of hashes, as eight bytes."""
    import numpy as np

    sums = np.zeros((len(first), 64), np.int64)
    ends = np.r_[first[1:], len(h)]
    lo = 0
    while lo < len(first):  # whole runs, about 2**14 hashes at once
        hi = max(lo + 1, int(np.searchsorted(ends, ends[lo] + (1 << 14))))
        if ends[hi - 1] - first[lo] <= 1 << 16:
            bits = np.unpackbits(h[first[lo] : ends[hi - 1]].astype(">u8").view(np.uint8).reshape(-1, 8), axis=1)
            sums[lo:hi] = np.add.reduceat(bits, first[lo:hi] - first[lo], axis=0, dtype=np.int64)
        else:
            for i in range(lo, hi):
                for at in range(first[i], ends[i], 1 << 16):
                    part = h[at : min(at + (1 << 16), ends[i])].astype(">u8").view(np.uint8).reshape(-1, 8)
                    sums[i] += np.unpackbits(part, axis=1).sum(0, dtype=np.int64)
        lo = hi
    return np.packbits(2 * sums > (ends - first)[:, None], axis=1)


def _distinct(h, no, n: int):
    """Different hashes of each text in rising order: (hashes, first place of
    each of the n texts, one place past the last)."""
    import numpy as np

    order = np.lexsort((h, no))
    h, no = h[order], no[order]
    keep = np.r_[True, (h[1:] != h[:-1]) | (no[1:] != no[:-1])] if len(h) else np.zeros(0, bool)
    h, no = h[keep], no[keep]
    return h, np.searchsorted(no, np.arange(n + 1))


def signatures(docs: DataFrame, s: Settings, id_col: str, text_col: str) -> DataFrame:
    """(id, k binary, n int, fp binary, keys array<long>): of every row the
    digest of its words, its number of different shingles, its SimHash and its
    band keys. A text without a word has no shingle, key or fingerprint bit."""
    kind = docs.schema[id_col].dataType.simpleString()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        import numpy as np

        for b in blocks(batches, "text", 1 << 20):
            texts = b.column("text").to_pylist()
            h, at = _distinct(*shingles(texts, s.words), len(texts))
            n = np.diff(at)
            some = np.flatnonzero(n)
            keys = np.zeros((len(texts), s.bands), np.int64)
            fp = np.zeros((len(texts), 8), np.uint8)
            if len(some):
                keys[some] = band_keys(h, at[some], s).view(np.int64)
                fp[some] = majority(h, at[some])
            lists = pa.ListArray.from_arrays(pa.array(np.r_[0, np.cumsum(np.where(n > 0, s.bands, 0))].astype(np.int32)), pa.array(keys[some].ravel()))
            cols = [b.column("id"), pa.array([words_digest(t) for t in texts], pa.binary()), pa.array(n, pa.int32()), pa.array([x.tobytes() for x in fp], pa.binary()), lists]
            yield pa.RecordBatch.from_arrays(cols, ["id", "k", "n", "fp", "keys"])

    rows = docs.select(F.col(id_col).alias("id"), text_or_empty(text_col).alias("text"))
    return rows.mapInArrow(run, f"id {kind}, k binary, n int, fp binary, keys array<long>")


def words_digest(text: str) -> bytes:
    from hashlib import blake2b

    return blake2b(b" ".join(text.encode("utf-8", "surrogatepass").lower().split()), digest_size=16).digest()


def size_ratio(similarity: float) -> float:
    """The least ratio of two sets' sizes at that cosine, which is at most the
    ratio's root; a little less, so that rounding leaves no exact case out."""
    return similarity**2 * (1 - 1e-9)


def _bucket_pairs(batches: Iterator[pa.RecordBatch], similarity: float) -> Iterator[pa.RecordBatch]:
    """Of rows sorted by (key, n, k): each member with the one before it, and
    with the least one of its bucket whose size still allows the similarity.
    What these leave apart is the business of ``_mixed_pairs``."""
    ratio = size_ratio(similarity)
    key = lead = last = None
    for b in batches:
        out = []
        for x, n, k in zip(b.column("key").to_pylist(), b.column("n").to_pylist(), b.column("k").to_pylist(), strict=True):
            if x != key:
                key, lead, last = x, (n, k), (n, k)
                continue
            for m, other in {last, lead}:
                if m >= ratio * n:
                    out.append((other, k))
            last = (n, k)
            if lead[0] < ratio * n:
                lead = last
        if out:
            yield pa.RecordBatch.from_arrays([pa.array([min(p) for p in out], pa.binary()), pa.array([max(p) for p in out], pa.binary())], ["a", "b"])


def _mixed_pairs(batches: Iterator[pa.RecordBatch], similarity: float, limit: int = 1 << 16) -> Iterator[pa.RecordBatch]:
    """Of rows sorted by (key, n, k), ``c`` telling a row's component: all pairs
    of a bucket whose sizes allow the similarity and whose components differ.
    ``_cell_links`` finds the links among them without making the pairs."""
    import numpy as np

    ratio = size_ratio(similarity)
    for t in _runs(batches, ["key", "n", "k", "c"]):
        key, n, k, c = (t.column(x).combine_chunks() if isinstance(t.column(x), pa.ChunkedArray) else t.column(x) for x in ("key", "n", "k", "c"))
        key, n, c = key.to_numpy(), n.to_numpy().astype(np.float64), c.to_numpy()
        start = np.flatnonzero(np.r_[True, key[1:] != key[:-1]])
        end = np.r_[start[1:], len(key)]
        mixed = np.minimum.reduceat(c, start) != np.maximum.reduceat(c, start)
        left, right, held = [], [], 0
        for s, e in zip(start[mixed].tolist(), end[mixed].tolist(), strict=True):
            low = s + np.searchsorted(n[s:e], ratio * n[s:e])
            for i in range(s + 1, e):
                at = np.flatnonzero(c[low[i - s] : i] != c[i]) + low[i - s]
                if len(at):
                    left.append(at)
                    right.append(np.full(len(at), i))
                    held += len(at)
                if held >= limit:
                    yield _ordered(k, left, right)
                    left, right, held = [], [], 0
        if held:
            yield _ordered(k, left, right)


def _mixed_rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """(bucket, k, c, b, home, of): the rows of buckets of several components.

    ``b`` is a row's block of the ``of`` of its bucket. The first ``home`` hold
    the component of most members alone, which has no pair within itself."""
    import numpy as np

    for t in _runs(batches, ["key", "n", "k", "c"]):
        key, n, c = (t.column(x).to_numpy() for x in ("key", "n", "c"))
        start = np.flatnonzero(np.r_[True, key[1:] != key[:-1]])
        end = np.r_[start[1:], len(key)]
        mixed = np.minimum.reduceat(c, start) != np.maximum.reduceat(c, start)
        rows, block, home, of = [], [], [], []
        for s, e in zip(start[mixed].tolist(), end[mixed].tolist(), strict=True):
            name, size = np.unique(c[s:e], return_counts=True)
            own = c[s:e] == name[size.argmax()]
            share = np.maximum(1 / BLOCK_ROWS, n[s:e] * (4 / BLOCK_SETS))
            at, first = np.zeros(e - s, np.int64), 0
            for part in (own, ~own):
                filled = np.cumsum(share[part])
                at[part] = first + np.unique(np.floor(filled - filled[0]), return_inverse=True)[1]
                first = int(at[part].max()) + 1
            rows.append(np.arange(s, e))
            block.append(at)
            home.append(np.full(e - s, at[own].max() + 1))
            of.append(np.full(e - s, first))
        if rows:
            at = np.concatenate(rows)
            cols = [pa.array(key[at]), t.column("k").take(pa.array(at)), pa.array(c[at]), *(pa.array(np.concatenate(x), pa.int32()) for x in (block, home, of))]
            yield from pa.table(cols, ["bucket", "k", "c", "b", "home", "of"]).combine_chunks().to_batches(1 << 14)


def _cells(rows: DataFrame) -> DataFrame:
    """Rows of ``_mixed_rows`` once for each cell (x, y) of two blocks that
    theirs meets another in; two blocks of the home component do not meet."""
    other = F.filter(F.sequence(F.lit(0), F.col("of") - 1), lambda o: (o != F.col("b")) & (F.greatest(o, "b") >= F.col("home")))
    met = rows.withColumn("o", F.explode(other))
    return met.select("bucket", F.least("o", "b").alias("x"), F.greatest("o", "b").alias("y"), "b", "k", "c")


def _cell_links(batches: Iterator[pa.RecordBatch], similarity: float) -> Iterator[pa.RecordBatch]:
    """(a, b): of whole cells, a row's ``key`` telling its cell and ``sh`` its
    set, a link of each text of block y to each other component that has one in
    block x, or in y itself where x is the first block."""
    import numpy as np

    for t in _runs(batches, ["key", "bucket", "x", "y", "b", "k", "c", "sh"]):
        bucket, x, y, b, c = (t.column(n).to_numpy() for n in ("bucket", "x", "y", "b", "c"))
        order = np.lexsort((y, x, bucket))
        name = np.stack([bucket, x, y])[:, order]
        new = np.flatnonzero(np.r_[True, (name[:, 1:] != name[:, :-1]).any(0)])
        for at in np.split(order, new[1:]):
            last, first = b[at] == y[at[0]], x[at[0]] == 0
            sets = [np.frombuffer(v, "<u4") for v in t.column("sh").take(pa.array(at)).to_pylist()]
            size = np.array([len(v) for v in sets])
            flat, owner = np.concatenate(sets), np.repeat(np.arange(len(at)), size)
            by = np.argsort(flat, kind="stable")
            flat, owner = flat[by], owner[by]
            left, right = [], []
            for i in np.flatnonzero(last).tolist():
                lo, hi = np.searchsorted(flat, sets[i]), np.searchsorted(flat, sets[i], "right")
                n = hi - lo
                both = np.bincount(owner[np.repeat(hi - np.cumsum(n), n) + np.arange(n.sum())], minlength=len(at))
                met = (c[at] != c[at[i]]) & (both / (size * float(size[i])) ** 0.5 >= similarity) & (~last | (first & (np.arange(len(at)) < i)))
                near = np.flatnonzero(met)
                if len(near):
                    near = near[np.unique(c[at[near]], return_index=True)[1]]  # the components are what links are for
                    left.append(at[near])
                    right.append(np.full(len(near), at[i]))
            if left:
                k = t.column("k")
                yield _ordered(k.combine_chunks() if isinstance(k, pa.ChunkedArray) else k, left, right)


def _ordered(k: pa.Array, left: list, right: list) -> pa.RecordBatch:
    """(a, b) with a < b of two lists of places in ``k``."""
    import numpy as np

    x, y = (k.take(pa.array(np.concatenate(p))).to_pylist() for p in (left, right))
    pairs = [(p, q) if p < q else (q, p) for p, q in zip(x, y, strict=True)]
    return pa.RecordBatch.from_arrays([pa.array([p for p, _ in pairs], pa.binary()), pa.array([q for _, q in pairs], pa.binary())], ["a", "b"])


def _bitmap(ids: DataFrame, bits: int) -> bytes:
    """Which cells of ``bits`` the hashes in the column ``h`` fall into; each
    task sends one bitmap of fixed size, eight of them reach the driver."""
    import numpy as np

    def own(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        seen = np.zeros(bits, bool)
        for b in batches:
            seen[(b.column("h").to_numpy().view(np.uint64) % np.uint64(bits)).astype(np.int64)] = True
        yield pa.RecordBatch.from_arrays([pa.array([np.packbits(seen).tobytes()], pa.binary())], ["m"])

    def both(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        seen = np.zeros(bits // 8, np.uint8)
        for b in batches:
            for m in b.column("m").to_pylist():
                seen |= np.frombuffer(m, np.uint8)
        yield pa.RecordBatch.from_arrays([pa.array([seen.tobytes()], pa.binary())], ["m"])

    out = np.zeros(bits // 8, np.uint8)
    for r in ids.mapInArrow(own, "m binary").repartition(8).mapInArrow(both, "m binary").collect():
        out |= np.frombuffer(r.m, np.uint8)
    return out.tobytes()


def shingle_sets(docs: DataFrame, ids: DataFrame, s: Settings, id_col: str, text_col: str) -> DataFrame:
    """(k binary, sh binary): the different shingles, 32 bits each in rising
    order, of the rows whose id is in ``ids`` (column id) and, as membership
    goes by a bitmap, of some others. Only those rows are read as words."""
    import numpy as np

    sent = docs.sparkSession.sparkContext.broadcast(_bitmap(ids.select(F.xxhash64("id").alias("h")), s.bitmap))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        wanted = np.unpackbits(np.frombuffer(sent.value, np.uint8))
        for whole in batches:
            cell = (whole.column("h").to_numpy().view(np.uint64) % np.uint64(s.bitmap)).astype(np.int64)
            for b in blocks(iter([whole.filter(pa.array(wanted[cell] > 0))]), "text", 1 << 20):
                texts = b.column("text").to_pylist()
                h, no = shingles(texts, s.words)
                h, at = _distinct(h >> np.uint64(32), no, len(texts))
                h = h.astype("<u4")
                sets = [h[a:z].tobytes() for a, z in zip(at, at[1:], strict=False)]
                yield pa.RecordBatch.from_arrays([pa.array([words_digest(t) for t in texts], pa.binary()), pa.array(sets, pa.binary())], ["k", "sh"])

    rows = docs.select(F.xxhash64(id_col).alias("h"), text_or_empty(text_col).alias("text"))
    return rows.mapInArrow(run, "k binary, sh binary").groupBy("k").agg(F.min("sh").alias("sh"))


def similarity_of(a: bytes, b: bytes) -> float:
    """Cosine of two sets of distinct shingles in rising order."""
    import numpy as np

    x, y = np.frombuffer(a, "<u4"), np.frombuffer(b, "<u4")
    if len(x) > len(y):
        x, y = y, x
    if not len(x):
        return float(not len(y))
    at = np.searchsorted(y, x)
    at[at == len(y)] = 0
    both = int((y[at] == x).sum())
    return both / (len(x) * len(y)) ** 0.5


def verified(pairs: DataFrame, sets: DataFrame, similarity: float) -> DataFrame:
    """The pairs (a, b) whose sets have the similarity."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            x, y = b.column("x").to_pylist(), b.column("y").to_pylist()
            yield b.filter(pa.array([similarity_of(p, q) >= similarity for p, q in zip(x, y, strict=True)], pa.bool_())).select(["a", "b"])

    left = sets.select(F.col("k").alias("a"), F.col("sh").alias("x"))
    right = sets.select(F.col("k").alias("b"), F.col("sh").alias("y"))
    return pairs.join(left, "a").join(right, "b").select("a", "b", "x", "y").mapInArrow(run, "a binary, b binary")


def bucket_rows(texts: DataFrame, *more: str) -> DataFrame:
    """(key, n, k, *more) of every text with a word: its bands and the group of
    its SimHash, in whole buckets sorted by (key, n, k)."""
    keys = texts.filter("n > 0").select(F.explode(F.array_append("keys", F.col("near"))).alias("key"), "n", "k", *more)
    return keys.repartition("key").sortWithinPartitions("key", "n", "k")


def simhash_groups(texts: DataFrame, s: Settings) -> tuple[DataFrame, DataFrame]:
    """(``texts`` with a column near, equal for all texts that SimHash links
    reach from each other; the links themselves as pairs a, b of digests)."""
    fps = stage(texts.filter("n > 0").groupBy("fp").agg(F.min("k").alias("first")), "near-fp").df
    found = stage(links(fps.select("fp"), s.simhash), "near-fp-links").df
    ends = fps.withColumnsRenamed({"fp": "a", "first": "ka"}), fps.withColumnsRenamed({"fp": "b", "first": "kb"})
    close = found.join(ends[0], "a").join(ends[1], "b").select(F.least("ka", "kb").alias("a"), F.greatest("ka", "kb").alias("b"))
    comps = components(found.select(F.lit(0).alias("rep"), F.xxhash64("a").alias("src"), F.xxhash64("b").alias("dst")))
    near = texts.withColumn("h", F.xxhash64("fp")).join(comps.select(F.col("v").alias("h"), "comp"), "h", "left")
    return near.withColumn("near", F.xxhash64(F.lit(2), F.coalesce("comp", "h"))).drop("h", "comp"), close


def candidates(texts: DataFrame, s: Settings, close: DataFrame | None = None) -> DataFrame:
    """(a, b): the first pairs of digests to look at, two for each text and
    bucket, and the SimHash links. ``texts`` has a row per different text
    (k, n, fp, keys), with near where the links ``close`` are known."""
    if close is None:
        texts, close = simhash_groups(texts, s)
    first = bucket_rows(texts).mapInArrow(lambda b: _bucket_pairs(b, s.similarity), "a binary, b binary")
    return first.unionByName(close).distinct()


def left_apart(texts: DataFrame, comps: DataFrame, sets: DataFrame, s: Settings) -> DataFrame:
    """(a, b): links between the components (v, comp) of texts that share a
    bucket. Each text of a mixed bucket is met with every other of it that is
    not in its component, on their real sets; of the links of a text to one
    component one is given."""
    placed = texts.join(comps.select(F.col("v").alias("k"), "comp"), "k", "left").withColumn("c", F.xxhash64(F.coalesce("comp", "k")))
    mixed = bucket_rows(placed, "c").mapInArrow(_mixed_rows, "bucket long, k binary, c long, b int, home int, of int")
    cells = _cells(stage(mixed, "near-mixed").df).join(sets, "k").withColumn("key", F.xxhash64("bucket", "x", "y"))
    met = cells.repartition("key").sortWithinPartitions("key")
    return met.mapInArrow(lambda b: _cell_links(b, s.similarity), "a binary, b binary").distinct()


def groups(docs: DataFrame, s: Settings | None = None, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(k binary, first, component): for each different text the least id that
    has it and the least id of its group of near copies.

    Texts of equal words (A-Z lower-cased, blanks aside) are one text; null
    texts are empty, and all texts without a word are one text that is near no
    other. Null ids count as greater than all. Other columns are not read.
    """
    s = s or Settings()
    sig = stage(signatures(docs, s, id_col, text_col), "near-signatures").df
    texts = stage(sig.groupBy("k").agg(F.min("id").alias("first"), *(F.any_value(c).alias(c) for c in ("n", "fp", "keys"))), "near-texts").df
    texts, close = simhash_groups(texts, s)
    texts = stage(texts, "near-texts").df
    pairs = stage(candidates(texts, s, close), "near-pairs").df
    busy = pairs.select(F.explode(F.array("a", "b")).alias("k")).distinct()
    sets = stage(shingle_sets(docs, texts.join(busy, "k", "left_semi").select(F.col("first").alias("id")), s, id_col, text_col), "near-sets").df
    # One pair of each text first: it settles most of what a large group has.
    least = pairs.groupBy("b").agg(F.min("a").alias("a")).select("a", "b")
    found = stage(verified(least, sets, s.similarity), "near-links").df
    comps = stage(star_components(found, "a", "b"), "near-comps").df
    a, b = comps.withColumnsRenamed({"v": "a", "comp": "ca"}), comps.withColumnsRenamed({"v": "b", "comp": "cb"})
    open_pairs = pairs.join(least, ["a", "b"], "left_anti").join(a, "a", "left").join(b, "b", "left").filter(F.coalesce("ca", "a") != F.coalesce("cb", "b")).select("a", "b")
    more = stage(verified(open_pairs, sets, s.similarity), "near-links").df
    found = found.unionByName(more)
    comps = stage(star_components(found, "a", "b"), "near-comps").df
    # Then every pair of a bucket that the links leave apart.
    last = stage(left_apart(texts, comps, sets, s), "near-links").df
    if not last.isEmpty():
        comps = stage(star_components(found.unionByName(last), "a", "b"), "near-comps").df
    comps = comps.withColumnsRenamed({"v": "k", "comp": "root"})
    rooted = texts.select("k", "first").join(comps, "k", "left").withColumn("root", F.coalesce("root", "k"))
    rooted = stage(rooted, "near-roots").df
    return rooted.join(rooted.groupBy("root").agg(F.min("first").alias("component")), "root").select("k", "first", "component")


def one_of_each(docs: DataFrame, s: Settings | None = None) -> DataFrame:
    """Rows of ``docs``, all columns, whose id is the least of a group of near
    copies. Rows that repeat an id stay or go together; rows without an id
    stay and stand for nobody; an empty table gives an empty one."""
    named = docs.filter(F.col("doc_id").isNotNull())
    stay = groups(named, s).select(F.col("component").alias("doc_id")).distinct()
    gone = stage(named.select("doc_id").distinct().join(stay, "doc_id", "left_anti"), "near-gone").df
    return docs.join(gone, "doc_id", "left_anti")
