"""Token totals kept up by signed deltas, batch by batch.

A store is a folder of tables of summed deltas and of commits that name them.
Inserts add, deletes subtract, a revised count subtracts the old amount under
its old key and adds the new one under its new key; totals are the sum of the
deltas. A batch is summed to a row per key, written to a folder of its own and
then claimed by the exclusive creation of one small file with the batch's name,
which holds the folder and a digest of the deltas. Of two writers of a batch
one gets the file; a batch that is replayed after a failure or delivered twice
changes nothing; one that comes again with other content is warned of.
"""

from __future__ import annotations

import uuid
import warnings
from dataclasses import dataclass

from py4j.protocol import Py4JJavaError
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from edgeconn.plans.staging import remove

KEYS = ("source", "lang", "tokenizer")
SCHEMA = "source string, lang string, tokenizer string, n_docs long, n_tokens long"


def _times(times: Column | None) -> Column:
    return (F.lit(1) if times is None else times).cast("long")


def insert(docs: DataFrame, tokenizer: str, count: Column, times: Column | None = None) -> DataFrame:
    """+1 document and +count tokens for every row, or ``times`` of both where
    a row stands for several; null counts are 0."""
    return docs.select("source", "lang", F.lit(tokenizer).alias("tokenizer"), _times(times).alias("n_docs"), (_times(times) * F.coalesce(count.cast("long"), F.lit(0).cast("long"))).alias("n_tokens"))


def delete(docs: DataFrame, tokenizer: str, count: Column, times: Column | None = None) -> DataFrame:
    """The opposite of ``insert``."""
    return insert(docs, tokenizer, count, times).withColumns({c: -F.col(c) for c in ("n_docs", "n_tokens")})


def revise(docs: DataFrame, old: tuple[str, Column], new: tuple[str, Column], times: Column | None = None) -> DataFrame:
    """Move every row's count from (tokenizer, count) ``old`` to ``new``, in
    one scan of ``docs``."""
    amount = lambda sign, t, c: F.struct(F.lit(t).alias("tokenizer"), (F.lit(sign) * _times(times)).alias("n_docs"), (F.lit(sign) * _times(times) * F.coalesce(c.cast("long"), F.lit(0).cast("long"))).alias("n_tokens"))
    both = F.explode(F.array(amount(-1, *old), amount(1, *new)))
    return docs.select("source", "lang", both.alias("d")).select("source", "lang", "d.*")


@dataclass(frozen=True)
class RollupStore:
    spark: SparkSession
    path: str

    def _fs(self, name: str):
        p = self.spark._jvm.org.apache.hadoop.fs.Path(f"{self.path}/{name}")
        return p.getFileSystem(self.spark._jsc.hadoopConfiguration()), p

    def _claim(self, batch: str) -> tuple[str, str] | None:
        """(folder, digest) of a committed batch."""
        fs, p = self._fs(f"commits/{batch}")
        if not fs.exists(p):
            return None
        stream = fs.open(p)
        try:
            text = bytes(self.spark._jvm.org.apache.hadoop.io.IOUtils.readFullyToByteArray(stream)).decode()
        finally:
            stream.close()
        folder, _, digest = text.partition(" ")
        if not digest.endswith("."):
            raise RuntimeError(f"the commit of {batch} was cut off while it was written; remove {p} and commit again")
        return folder, digest[:-1]

    def committed(self, batch: str) -> bool:
        return self._claim(batch) is not None

    def commit(self, batch: str, deltas: DataFrame) -> bool:
        """Add a batch; False, and no change, if it is in already.

        What an unfinished or beaten try wrote is never read. Keys may be null;
        rows of any number per key are summed before the shuffle. A batch that
        is in with other sums is warned of.
        """
        folder = f"try-{uuid.uuid4().hex}"
        total = deltas.groupBy(*KEYS).agg(*(F.sum(c).alias(c) for c in ("n_docs", "n_tokens")))
        total.write.parquet(f"{self.path}/{folder}")
        row = self.spark.read.schema(SCHEMA).parquet(f"{self.path}/{folder}").agg(F.count(F.lit(1)).alias("n"), F.coalesce(F.bit_xor(F.xxhash64(*KEYS, "n_docs", "n_tokens")), F.lit(0)).alias("x")).first()
        digest = f"{row.n}:{row.x}"
        fs, p = self._fs(f"commits/{batch}")
        fs.mkdirs(p.getParent())
        if not fs.exists(p):
            try:
                stream = fs.create(p, False)  # exclusive: one writer gets it
            except Py4JJavaError:
                stream = None
            if stream is not None:
                stream.write(bytearray(f"{folder} {digest}.".encode()))
                stream.close()
                return True
        known = self._claim(batch)
        remove(self.spark, f"{self.path}/{folder}")
        if known is not None and known[1] != digest:
            warnings.warn(f"batch {batch} came again with other content, which is not taken", stacklevel=2)
        return False

    def batches(self) -> list[str]:
        fs, p = self._fs("commits")
        if not fs.exists(p):
            return []
        names = [s.getPath().getName() for s in fs.listStatus(p)]
        return sorted(n for n in names if not n.startswith("."))

    def totals(self) -> DataFrame:
        """Totals per key over the committed batches; keys that came to
        nothing are left out."""
        paths = [f"{self.path}/{self._claim(b)[0]}" for b in self.batches()]
        deltas = self.spark.read.schema(SCHEMA).parquet(*paths) if paths else self.spark.createDataFrame([], SCHEMA)
        out = deltas.groupBy(*KEYS).agg(*(F.sum(c).alias(c) for c in ("n_docs", "n_tokens")))
        return out.filter((F.col("n_docs") != 0) | (F.col("n_tokens") != 0))


def words(text: Column) -> Column:
    """Tokenizer ``words-1``: runs of characters other than ASCII whitespace."""
    plain = F.regexp_replace(text, "[\\x20\\x09-\\x0D]+", " ")
    trimmed = F.trim(plain)
    return F.when(F.length(trimmed) == 0, 0).otherwise(F.length(trimmed) - F.length(F.replace(trimmed, F.lit(" "), F.lit(""))) + 1)


def words_and_marks(text: Column) -> Column:
    """Tokenizer ``words-2``: as ``words``, and each ASCII mark on its own."""
    spaced = F.regexp_replace(text, "([!-/:-@\\[-`{-~])", " $1 ")
    return words(spaced)


ORACLE_SQL = r"""
WITH d AS (SELECT doc_id, source, lang, coalesce(text, '') AS t FROM documents),
k AS (SELECT *, min(doc_id) OVER (PARTITION BY t) AS first FROM d),
n AS (SELECT source, lang, len(regexp_extract_all(regexp_replace(t, '([!-/:-@\[-`{-~])', ' \1 ', 'g'), '[^\x20\x09-\x0D]+')) AS c
      FROM k WHERE doc_id = first)
SELECT source, lang, 'words-2' AS tokenizer, count(*) AS n_docs, CAST(sum(c) AS BIGINT) AS n_tokens FROM n GROUP BY source, lang
"""
