"""Document fingerprints of closed syncmers with positional matching.

A k-mer of characters is a closed syncmer where the least of its inner s-mers
(by hash) is its first or its last. That depends on the k-mer's own characters
alone, so an edit elsewhere never changes which anchors a passage has. A
fingerprint holds a text's anchors with their places: all of them up to
``keep``, and of longer texts those whose hash lies under a bound that leaves
at least ``keep`` and at least one of ``share``. Two fingerprints are alike by
the share of their anchors, under the lesser bound of both, that they have in
common at a consistent shift.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F


@dataclass(frozen=True)
class Settings:
    """k, s: lengths of anchors and inner s-mers. keep, share: a fingerprint
    has all of up to ``keep`` anchors, and of more the ``keep`` of least hash
    or one in ``share``, whichever is more. slack: how far places may differ
    from the common shift, in characters."""

    k: int = 16
    s: int = 6
    keep: int = 128
    share: int = 8
    slack: int = 64


def _rolling(codes, n: int):
    """Hash of the n characters from each place on, finalised."""
    import numpy as np

    h = np.zeros(len(codes) - n + 1, np.uint64)
    for j in range(n):
        h = h * np.uint64(0x9E3779B97F4A7C15) + codes[j : len(codes) - n + 1 + j] + np.uint64(1)
    h = (h ^ (h >> np.uint64(29))) * np.uint64(0xBF58476D1CE4E5B9)
    return h ^ (h >> np.uint64(32))


def anchors(text: str, s: Settings):
    """(hash, place) of every closed syncmer of the text, in order. A text too
    short for a k-mer is one anchor; an empty text has none."""
    import numpy as np

    codes = np.frombuffer(text.encode("utf-32-le", "surrogatepass"), np.uint32).astype(np.uint64)
    if len(codes) < s.k:
        whole = _rolling(codes, len(codes)) if len(codes) else np.zeros(0, np.uint64)
        return whole, np.zeros(len(whole), np.int64)
    inner = _rolling(codes, s.s)
    span = s.k - s.s + 1
    least, width = inner, 1  # minimum over [i, i + width)
    while width * 2 <= span:
        least = np.minimum(least[: len(least) - width], least[width:])
        width *= 2
    n = len(codes) - s.k + 1
    least = np.minimum(least[:n], least[span - width : span - width + n])
    at = np.flatnonzero((least == inner[:n]) | (least == inner[span - 1 : span - 1 + n]))
    h = np.zeros(len(at), np.uint64)
    for j in range(s.k):
        h = h * np.uint64(0x9E3779B97F4A7C15) + codes[at + j] + np.uint64(1)
    h = (h ^ (h >> np.uint64(31))) * np.uint64(0x94D049BB133111EB)
    return h ^ (h >> np.uint64(32)), at


def sketch(text: str, s: Settings):
    """The kept anchors: 32-bit hashes in rising order, first place of each,
    and the bound under which every anchor's hash is kept."""
    import numpy as np

    h, at = anchors(text, s)
    u, first = np.unique(h >> np.uint64(32), return_index=True)
    bound = 1 << 32 if len(u) <= s.keep else max((1 << 32) // s.share, int(u[s.keep - 1]) + 1)
    n = int(np.searchsorted(u, bound))
    return u[:n].astype(np.uint32), at[first[:n]], bound


def encode(sk) -> str:
    """Fixed text form: the bound, then eight hex digits and the place of each
    kept anchor."""
    return " ".join([f"{sk[2]:x}", *(f"{h:08x}:{p:x}" for h, p in zip(sk[0].tolist(), sk[1].tolist(), strict=True))])


def decode(text: str):
    import numpy as np

    bound, *pairs = text.split()
    pairs = [x.split(":") for x in pairs]
    return np.array([int(a, 16) for a, _ in pairs], np.uint32), np.array([int(b, 16) for _, b in pairs], np.int64), int(bound, 16)


def likeness(a, b, s: Settings) -> float:
    """Share of the joint sketch in both at the commonest shift, 0 to 1.

    Of the anchors under the lesser bound, which both sketches hold whole,
    those in both whose places differ by the commonest difference, within
    ``slack``, count. Equal sketches give 1, two empty ones too; an empty and
    another give 0.
    """
    import numpy as np

    bound = min(a[2], b[2])
    (ha, pa_), (hb, pb) = ((x[0][: np.searchsorted(x[0], bound)], x[1]) for x in (a, b))
    if not len(ha) or not len(hb):
        return float(len(ha) == len(hb))
    both = np.intersect1d(ha, hb, assume_unique=True)
    if not len(both):
        return 0.0
    shift = np.sort(pa_[np.searchsorted(ha, both)] - pb[np.searchsorted(hb, both)])
    most = int((np.searchsorted(shift, shift + s.slack, "right") - np.arange(len(shift))).max())
    return most / (len(ha) + len(hb) - len(both))


def edited(text: str, following: str) -> str:
    """The text with its last half put over by the start of the following."""
    half = len(text) // 2
    new = following[:half]
    return text[: len(text) - half] + new


def edited_neighbours(docs: DataFrame, s: Settings | None = None, ranges: int | None = None) -> DataFrame:
    """(id, n_chars, edited_sha256, fingerprint, edited_fingerprint,
    near_edited, near_next), one row per row of ``docs``.

    The next document is the next in descending doc_id; the last one's is the
    first. Null ids come last, equal ids go by text, a null text is empty, and
    a sole document follows itself. Ranges are cut by id and first characters,
    so that rows of one id, or of none, are dealt too. Every text is moved
    once, to its range; the first document of each range is also sent to the
    range before, so that each range's last document meets its next.
    """
    s = s or Settings()
    spark = docs.sparkSession
    rows = docs.select("doc_id", F.bitwise_not(F.coalesce(F.col("doc_id").cast("long"), F.lit(-(1 << 63)))).alias("r"), F.coalesce("text", F.lit("")).alias("text")).withColumn("p", F.substring("text", 1, 32))
    n = ranges or max(1, int(spark.conf.get("spark.sql.shuffle.partitions")) * 2)
    ranged = rows.select("r", "p").repartitionByRange(n, "r", "p")
    heads = sorted((x.m.r, x.m.p) for x in ranged.groupBy(F.spark_partition_id()).agg(F.min(F.struct("r", "p")).alias("m")).collect() if x.m)  # a row per range
    own, is_head = _range_of(heads[1:], heads[0] if heads else (0, ""))
    go = F.filter(
        F.array(F.struct(own.alias("to"), F.lit(0).alias("ghost")), F.struct(F.when(is_head, F.pmod(own - 1, F.lit(max(1, len(heads))))).otherwise(-1).alias("to"), F.lit(1).alias("ghost"))),
        lambda x: x["to"] >= 0,
    )
    sent = rows.select("doc_id", "r", "p", "text", F.explode(go).alias("go")).select("doc_id", "r", "p", "text", "go.to", "go.ghost")
    placed = sent.repartition(n, "to").sortWithinPartitions("to", "ghost", "r", "p", "text").drop("r", "p")
    kind = docs.schema["doc_id"].dataType.simpleString()
    schema = f"id {kind}, n_chars long, edited_sha256 string, fingerprint string, edited_fingerprint string, near_edited double, near_next double"

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from hashlib import sha256

        out: list[list] = []
        held = None  # (range, id, text, sketch) of the row before

        def emit(held, following: str, next_sketch):
            _, i, t, sk = held
            e = edited(t, following)
            se = sketch(e, s)
            out.append([i, len(t), sha256(e.encode("utf-8", "surrogatepass")).hexdigest(), encode(sk), encode(se), likeness(sk, se, s), likeness(sk, next_sketch, s)])

        def flush():
            cols = list(zip(*out, strict=True))
            types = [id_type, pa.int64(), pa.string(), pa.string(), pa.string(), pa.float64(), pa.float64()]
            made = pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(cols, types, strict=True)], ["id", "n_chars", "edited_sha256", "fingerprint", "edited_fingerprint", "near_edited", "near_next"])
            out.clear()
            return made

        id_type = None
        for b in batches:
            id_type = b.schema.field("doc_id").type
            for i in range(b.num_rows):
                to, t = b.column("to")[i].as_py(), b.column("text")[i].as_py()
                sk = sketch(t, s)
                if held is not None and held[0] == to:
                    emit(held, t, sk)
                    held = None
                if not b.column("ghost")[i].as_py():
                    held = (to, b.column("doc_id")[i].as_py(), t, sk)
                if len(out) >= 2000:
                    yield flush()
        if out:
            yield flush()

    return placed.mapInArrow(run, schema)


def _range_of(bounds: list[tuple[int, str]], first: tuple[int, str]):
    """(range, whether it begins the range) of the key (r, p): how many of the
    rising bounds are not over it, sought among every so manieth bound and
    then among those between."""
    key = F.struct("r", "p")
    made = lambda xs: F.array(*(F.struct(F.lit(r).cast("long").alias("r"), F.lit(p).alias("p")) for r, p in xs))
    if not bounds:
        return F.lit(0), key == made([first])[0]
    step = max(1, int(len(bounds) ** 0.5))
    under = lambda xs: F.size(F.filter(xs, lambda b: b <= key))
    coarse = under(made(bounds[::step]))
    fine = under(F.slice(made(bounds), (coarse - 1) * step + 1, step))
    own = F.when(coarse == 0, F.lit(0)).otherwise((coarse - 1) * step + fine)
    return own, F.element_at(made([first, *bounds]), own + 1) == key
