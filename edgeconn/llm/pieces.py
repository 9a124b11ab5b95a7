"""SentencePiece encoding and decoding through a table of distinct chunks.

A chunk is a run of whitespace markers with the characters up to the next run.
No piece of the vocabulary has a marker after another character, so no merge
crosses from one chunk to the next: each distinct chunk is segmented once and
its ids are joined back by position, with the library's own result.
"""

from __future__ import annotations

from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from edgeconn.llm.common import blocks, text_or_empty

MARK = "▁"
#: Chunks that a worker's table holds before it starts anew; results do not depend on it.
TABLE = 100_000


def default_model() -> str:
    import public_tokenizers

    return public_tokenizers.path("piece_bpe_32k.model")


def model_bytes(path: str) -> bytes:
    with open(path, "rb") as f:
        return f.read()


def chunkable(model: bytes) -> bool:
    """Whether chunks of this model can be segmented apart."""
    from sentencepiece import sentencepiece_model_pb2 as proto

    m = proto.ModelProto()
    m.ParseFromString(model)
    n = m.normalizer_spec
    plain = n.name == "identity" and not n.precompiled_charsmap and n.add_dummy_prefix and not n.remove_extra_whitespaces and n.escape_whitespaces
    inner = any(MARK in p.piece.lstrip(MARK) for p in m.pieces)
    return plain and not inner and not m.trainer_spec.treat_whitespace_as_suffix and not any(p.type == 4 for p in m.pieces)


class ChunkTable:
    """What each distinct chunk gives to the outputs asked for: its ids, the
    ids as text or packed, its decoded text. Only those are held."""

    def __init__(self, model: bytes, parts: tuple[str, ...] = ("ids", "decoded")):
        import re

        import sentencepiece

        self.sp = sentencepiece.SentencePieceProcessor(model_proto=model)
        self.cut = re.compile(" +[^ ]*").findall
        self.code = "H" if self.sp.vocab_size() <= 1 << 16 else "I"
        self.size: dict[str, int] = {}
        self.parts: dict[str, dict] = {p: {} for p in parts}

    def chunks(self, text: str) -> list[str]:
        return self.cut(" " + text.replace(MARK, " ")) if text else []

    def learn(self, chunks: set[str]) -> None:
        from struct import pack

        if len(self.size) > TABLE:
            for t in (self.size, *self.parts.values()):
                t.clear()
        new = [c for c in chunks if c not in self.size]
        for i in range(0, len(new), 8192):
            part = new[i : i + 8192]
            # a lone marker, at the end of a text, is a piece of its own
            found = [ids or [self.sp.piece_to_id(MARK)] for ids in self.sp.encode([c[1:] for c in part], num_threads=1)]
            self.size.update(zip(part, map(len, found), strict=True))
            made = {
                "ids": lambda found=found: found,
                "joined": lambda found=found: [",".join(map(str, ids)) for ids in found],
                "packed": lambda found=found: [pack(f"<{len(ids)}{self.code}", *ids) for ids in found],
                "decoded": lambda found=found: [" " + t for t in self.sp.decode(found)],
            }
            for p, t in self.parts.items():
                t.update(zip(part, made[p](), strict=True))

    def count(self, chunks: list[str]) -> int:
        return sum(map(self.size.__getitem__, chunks))

    def each(self, part: str, chunks: list[str]):
        """The part of every chunk, in order."""
        return map(self.parts[part].__getitem__, chunks)

    def encode(self, chunks: list[str]) -> list[int]:
        return [i for ids in self.each("ids", chunks) for i in ids]

    def decode(self, chunks: list[str]) -> str:
        return "".join(self.each("decoded", chunks))[1:]


def encode_decode(docs: DataFrame, model_path: str | None = None, outputs: tuple[str, ...] = ("ids", "decoded"), id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(id, n_tokens long, then the ``outputs`` asked for), one row per row.

    outputs: ``ids`` array<int>, ``decoded`` string, ``ids_sha256`` of the
    decimal ids joined by commas, ``decoded_sha256`` of the decoded UTF-8,
    ``packed`` binary: the ids as little-endian numbers of two bytes each (four
    where the vocabulary is over 65,536), which training readers map as they are.
    Null and empty texts have no token and decode to an empty text. Texts are
    read whole; other columns are not read.
    """
    kinds = {"ids": ("array<int>", pa.list_(pa.int32())), "decoded": ("string", pa.string()), "packed": ("binary", pa.binary()), "ids_sha256": ("string", pa.string()), "decoded_sha256": ("string", pa.string())}
    model = model_bytes(model_path or default_model())
    if not chunkable(model):
        raise ValueError("pieces of this model may cross whitespace markers")
    kind = docs.schema[id_col].dataType.simpleString()
    sent = docs.sparkSession.sparkContext.broadcast(model)  # one vocabulary file

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from hashlib import sha256

        needs = {"ids": "ids", "decoded": "decoded", "packed": "packed", "ids_sha256": "joined", "decoded_sha256": "decoded"}
        table = ChunkTable(sent.value, tuple({needs[o]: None for o in outputs}))
        made = {
            "ids": table.encode,
            "decoded": table.decode,
            "packed": lambda c: b"".join(table.each("packed", c)),
            "ids_sha256": lambda c: sha256(",".join(table.each("joined", c)).encode()).hexdigest(),
            "decoded_sha256": lambda c: sha256(table.decode(c).encode()).hexdigest(),
        }
        for b in blocks(batches, "text", 2 << 20):
            texts = [table.chunks(t) for t in b.column("text").to_pylist()]
            table.learn(set().union(*texts))
            cols = [b.column("id"), pa.array(list(map(table.count, texts)), pa.int64())]
            cols += [pa.array([made[o](c) for c in texts], kinds[o][1]) for o in outputs]
            yield pa.RecordBatch.from_arrays(cols, ["id", "n_tokens", *outputs])

    schema = ", ".join([f"id {kind}, n_tokens long", *(f"{o} {kinds[o][0]}" for o in outputs)])
    return docs.select(F.col(id_col).alias("id"), text_or_empty(text_col).alias("text")).mapInArrow(run, schema)
