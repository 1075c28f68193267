"""Token ids as ORC: integer run-length encoded stripes with row indexes and Bloom filters on ids.

Documents are dealt to tasks by ranges of ``doc_id`` (ties by a hash of the text, so a repeated id
can be split), sorted, encoded and written in ascending order.  Each row holds the ids of one
document, the task it was written by and the number of ids before it in that task, so the global
start follows from one total per task.  Readers split files at stripes; ranges and lists of ids
reach the stripe statistics, row indexes and Bloom filters as pushed filters.

White space never reaches the vocabulary, so texts are cut at ASCII white space and each distinct
chunk is encoded once by the tokenizers library and remembered, within a bound.

Rows: null text counts as empty (only the end id); a null ``doc_id`` sorts first; repeated rows
are written each; an empty table gives an empty table.
"""

from __future__ import annotations

import functools
import os
import unicodedata
import zlib
from array import array

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from phasewarp.llm.bpe import byte_alphabet
from phasewarp.llm.common import documents, shared_folder, shuffle_width

_STAND_INS = {b: c for c, b in byte_alphabet().items()}
END_ID = 1
CACHE_CHUNKS = 400_000
BATCH_CHARS = 4_000_000
ORC_OPTIONS = {
    "compression": "zstd",
    "orc.bloom.filter.columns": "doc_id",
    "orc.bloom.filter.fpp": "0.01",
    "orc.create.index": "true",
    "orc.row.index.stride": "2000",
    "orc.stripe.size": str(32 << 20),
    "orc.encoding.strategy": "SPEED",
}
ROW = "doc_id long, part int, before long, ids array<int>"


class ChunkEncoder:
    """Ids of texts as little-endian 32-bit bytes, by remembered white-space-free chunks.

    A chunk that is not known is looked up again without its closing ASCII punctuation, which the
    vocabulary's split pattern never joins to a letter or digit before it.
    """

    def __init__(self, path: str):
        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        from tokenizers import Tokenizer

        self.tokenizer = Tokenizer.from_file(path)
        self.tokenizer.no_padding()
        self.tokenizer.no_truncation()
        self.batch = getattr(self.tokenizer, "encode_batch_fast", self.tokenizer.encode_batch)
        self.merge = self.tokenizer.model.tokenize
        self.young: dict[bytes, bytes] = {}
        self.old: dict[bytes, bytes] = {}

    def __call__(self, text: str | None) -> bytes:
        return self.encode_all([text])[0]

    def encode_all(self, texts: list[str | None]) -> list[bytes]:
        split = [self._split(t) for t in texts]
        asked = set().union(*split)
        if len(self.young) + len(asked) // 4 > CACHE_CHUNKS:  # the young generation turns old; what is asked for moves back
            self.young, self.old = {}, self.young
        self._learn(asked.difference(self.young))
        get = self.young.__getitem__
        return [b"".join(map(get, chunks)) for chunks in split]

    @staticmethod
    def _split(text: str | None) -> list[bytes]:
        data = (text or "").encode("utf-8", "surrogatepass")
        # lower-casing early lets more chunks meet; not where special tokens may be spelled
        return data.split() if b"<|" in data else data.lower().split()

    def _as_is(self, chunk: bytes) -> str | None:
        """The chunk in the model's byte alphabet if it is one lower-case word that the normaliser
        and the split pattern leave as it is, so that the library's merges alone encode it."""
        if chunk.isalpha():
            return chunk.decode() if chunk.islower() else None
        word = chunk.decode("utf-8", "replace")
        if word.isalpha() and max(word) < "\u0250" and word == word.lower() and unicodedata.is_normalized("NFC", word):
            return chunk.decode("latin-1").translate(_STAND_INS)
        return None

    def _learn(self, fresh: set[bytes]) -> None:
        young, old, whole, cut, wanted = self.young, self.old, [], [], set()
        for c in fresh:
            ids = old.get(c)
            if ids is not None:
                young[c] = ids
                continue
            core = c.rstrip(b".,;:!?")
            if len(core) == len(c) or not (core[-1:].isalnum() or core.decode("utf-8", "replace")[-1:].isalpha()) or b"<|" in core:
                whole.append(c)
                continue
            end = c[len(core) :]
            cut.append((c, core, end))
            for part in (core, end):
                if part not in young:
                    ids = old.get(part)
                    if ids is None:
                        wanted.add(part)
                    else:
                        young[part] = ids
        wanted.update(whole)
        unknown = []
        for c in wanted:
            plain = self._as_is(c)
            if plain is None:
                unknown.append(c)
            else:
                young[c] = array("I", [t.id for t in self.merge(plain)]).tobytes()
        for at in range(0, len(unknown), 4096):
            part = unknown[at : at + 4096]
            for c, e in zip(part, self.batch([c.decode("utf-8", "replace") for c in part], add_special_tokens=False)):
                young[c] = array("I", e.ids).tobytes()
        for c, core, end in cut:
            young[c] = young[core] + young[end]


@functools.lru_cache(2)
def _encoder(path: str) -> ChunkEncoder:
    return ChunkEncoder(path)


def _encode_batches(path: str, end_id: int):
    tail = np.array([end_id], "<u4").tobytes()

    def run(batches):
        from pyspark import TaskContext

        encode, part, before = _encoder(path), TaskContext.get().partitionId(), 0
        for b in batches:
            for docs, texts in _slices(b):
                ids = [data + tail for data in encode.encode_all(texts)]
                lengths = [len(d) // 4 for d in ids]
                starts = (before + np.cumsum([0, *lengths[:-1]])).tolist()
                before += sum(lengths)
                yield _ids_batch(docs, part, starts, lengths, ids)

    return run


def _slices(b: pa.RecordBatch):
    """Ids and texts of a batch in runs of bounded size."""
    docs, texts, held = [], [], 0
    for doc, text in zip(b.column("doc_id").to_pylist(), b.column("text")):
        docs.append(doc)
        texts.append(text.as_py())
        held += len(texts[-1] or "")
        if held >= BATCH_CHARS:
            yield docs, texts
            docs, texts, held = [], [], 0
    if docs:
        yield docs, texts


def _ids_batch(rows, part, starts, lengths, ids) -> pa.RecordBatch:
    offsets = np.concatenate(([0], np.cumsum(lengths))).astype(np.int32)
    values = pa.array(np.frombuffer(b"".join(ids), "<i4"), pa.int32())
    return pa.RecordBatch.from_arrays(
        [pa.array(rows, pa.int64()), pa.array([part] * len(rows), pa.int32()), pa.array(starts, pa.int64()), pa.ListArray.from_arrays(pa.array(offsets), values)],
        names=["doc_id", "part", "before", "ids"],
    )


def write_tokens(docs: DataFrame, tokenizer: str, path: str, end_id: int = END_ID, parts: int | None = None) -> None:
    """Encode ``docs(doc_id, text)`` and write them to ``path`` in ascending ``doc_id`` order."""
    (
        docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
        .withColumn("tie", F.xxhash64("text"))
        .repartitionByRange(parts or shuffle_width(docs.sparkSession), F.col("doc_id").asc_nulls_first(), "tie")
        .sortWithinPartitions(F.col("doc_id").asc_nulls_first(), "tie")
        .select("doc_id", "text")
        .mapInArrow(_encode_batches(tokenizer, end_id), ROW)
        .write.options(**ORC_OPTIONS)
        .orc(path)
    )


def read_tokens(spark: SparkSession, path: str) -> DataFrame:
    return spark.read.schema(ROW).orc(path)


def lookup(spark: SparkSession, path: str, doc_ids: list[int]) -> DataFrame:
    """Rows of the ids asked for; Bloom filters and row indexes skip what cannot hold them."""
    return read_tokens(spark, path).filter(F.col("doc_id").isin(doc_ids))


def read_range(spark: SparkSession, path: str, first: int, last: int) -> DataFrame:
    """Rows with ``first <= doc_id <= last``; stripe statistics skip the rest."""
    return read_tokens(spark, path).filter(F.col("doc_id").between(first, last))


def _digest_batches(batches):
    for b in batches:
        lists = b.column("ids")
        offsets = lists.offsets.to_numpy()
        data = memoryview(np.ascontiguousarray(lists.values.to_numpy(zero_copy_only=False), dtype="<i4")).cast("B")
        crc = [zlib.crc32(data[4 * x : 4 * y]) for x, y in zip(offsets[:-1].tolist(), offsets[1:].tolist())]
        yield pa.RecordBatch.from_arrays(
            [b.column("doc_id"), b.column("part"), b.column("before"), pa.array(np.diff(offsets).astype(np.int64)), pa.array(crc, pa.int64())],
            names=["doc_id", "part", "before", "n_tokens", "ids_crc32"],
        )


def digest(spark: SparkSession, path: str) -> DataFrame:
    """``doc_id, start, n_tokens, ids_crc32`` from the files; one total per written task is
    all that is broadcast."""
    rows = read_tokens(spark, path)
    ends = rows.groupBy("part").agg(F.max(F.col("before") + F.size("ids")).alias("n"))
    starts = ends.select("part", F.coalesce(F.sum("n").over(Window.orderBy("part").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("base"))
    return (
        rows.mapInArrow(_digest_batches, "doc_id long, part int, before long, n_tokens long, ids_crc32 long")
        .join(F.broadcast(starts), "part")
        .select("doc_id", (F.col("base") + F.col("before")).alias("start"), "n_tokens", "ids_crc32")
    )


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    import public_tokenizers

    path = f"{shared_folder(spark)}/tokens.orc"
    write_tokens(documents(spark, sf_dir), public_tokenizers.path("word_bpe_49k.json"), path)
    return digest(spark, path)
