"""Byte-level BPE by backtracking over longest matches, and decoding by an offset table.

A piece of text is scanned once by an Aho-Corasick automaton over all tokens, which gives the
longest token at every position.  Tokens are then taken from the left; two neighbours are allowed
only if merging their joined bytes gives exactly these two (the pair-compatibility table, filled
as pairs turn up).  A refused token gives way to its longest proper prefix that is a token, and
when none is left the previous token is taken back and the position is marked dead, so every
position is left at most once: linear time, and exactly the merges' result.

Pieces are the pre-tokens of the vocabulary's split pattern.  Texts are first cut into chunks of
one optional space and a run of other characters, which the pattern never crosses; ids of a chunk
are remembered within a bound.  Texts with white space outside ASCII take the pattern as a whole.
The special tokens' strings in a text become their ids, as in the tokenizers library.

Rows: null text counts as empty and has no ids; repeated rows and very long texts are encoded
like any others; extra columns pass through; an empty table gives an empty table.
"""

from __future__ import annotations

import array
import functools
import json
import re

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from phasewarp.llm.common import documents, release

GENERATION = 120_000
MOST_PAIRS = 300_000
LONGEST_KEY = 128
BATCH_IDS = 2_000_000
_ASCII_WS = r" \t\n\r\x0b\x0c"
#: White space of Unicode outside ASCII.
_WIDE_WS = "\x85\xa0\u1680\u2000-\u200a\u2028\u2029\u202f\u205f\u3000"
_OTHER_WS = re.compile(f"[{_WIDE_WS}]")
_CHUNK = re.compile(rf" ?[^{_ASCII_WS}]+|[{_ASCII_WS}]+(?![^{_ASCII_WS}])|[{_ASCII_WS}]+")


def byte_alphabet() -> dict[str, int]:
    """Printable stand-ins of the 256 bytes: themselves where visible, else from U+0100 on."""
    seen = [*range(33, 127), *range(161, 173), *range(174, 256)]
    table = {chr(b): b for b in seen}
    rest = (b for b in range(256) if b not in set(seen))
    return table | {chr(256 + k): b for k, b in enumerate(rest)}


class Remembered(dict):
    """Values of ``make`` by key in two generations: when the young one is full it becomes the old
    one, and what is asked for again moves over, so frequent keys stay and memory is bounded.  Long
    keys are made anew each time."""

    def __init__(self, make, most: int = GENERATION):
        super().__init__()
        self.make, self.most, self.old = make, most, {}

    def __missing__(self, key: str):
        value = self.old.get(key)
        if value is None:
            value = self.make(key)
        if len(key) <= LONGEST_KEY:
            if len(self) >= self.most:
                self.old = dict(self)
                self.clear()
            self[key] = value
        return value


class Vocabulary:
    """Tokens of a byte-level BPE file and the offset table that decodes them."""

    def __init__(self, path: str):
        with open(path, encoding="utf-8") as f:
            self.read(json.load(f))

    def read(self, spec: dict) -> None:
        byte_of = byte_alphabet()
        self.raw = lambda token: bytes(byte_of[c] for c in token)
        self.special = {t["content"]: t["id"] for t in spec["added_tokens"]}
        bytes_of = {i: self.raw(t) for t, i in spec["model"]["vocab"].items() if t not in self.special}
        bytes_of |= {i: t.encode() for t, i in self.special.items()}
        parts = [bytes_of.get(i, b"") for i in range(max(bytes_of) + 1)]
        self.offsets = np.concatenate(([0], np.cumsum([len(p) for p in parts]))).astype(np.int64)
        self.table = np.frombuffer(b"".join(parts), np.uint8)

    def decode(self, ids: np.ndarray) -> bytes:
        """Bytes of the ids, gathered from the table at each id's offset."""
        if not len(ids):
            return b""
        starts = self.offsets[ids]
        sizes = self.offsets[ids + 1] - starts
        ends = np.cumsum(sizes)
        return self.table[np.repeat(starts - (ends - sizes), sizes) + np.arange(ends[-1])].tobytes()


class BacktrackingBpe(Vocabulary):
    def read(self, spec: dict) -> None:
        import ahocorasick
        import regex

        super().read(spec)
        raw = self.raw
        self.id_of = {raw(t): i for t, i in spec["model"]["vocab"].items() if t not in self.special}
        self.bytes_of = {i: b for b, i in self.id_of.items()} | {i: t.encode() for t, i in self.special.items()}
        self.rank = {}
        for k, pair in enumerate(spec["model"]["merges"]):
            a, b = pair.split(" ") if isinstance(pair, str) else pair
            self.rank[raw(a), raw(b)] = k
        self.halves, self.made_at, self.joins = {}, {}, {}
        for (a, b), k in self.rank.items():
            x, y, z = self.id_of[a], self.id_of[b], self.id_of[a + b]
            self.joins[x, y] = k
            if z not in self.made_at:
                self.halves[z], self.made_at[z] = (x, y), k
        self.automaton = ahocorasick.Automaton()
        for b, i in self.id_of.items():
            if len(b) == 1 or self.merge(b) == [i]:
                self.automaton.add_word(b.decode("latin-1"), (i, len(b)))
        self.automaton.make_automaton()
        self.shorter: dict[int, int | None] = {}
        self.pairs: dict[tuple[int, int], bool] = {}
        ws = _ASCII_WS + _WIDE_WS
        self.split = regex.compile(rf"'s|'t|'re|'ve|'m|'ll|'d| ?\p{{L}}+| ?\p{{N}}+| ?[^{ws}\p{{L}}\p{{N}}]+|[{ws}]+(?![^{ws}])|[{ws}]+").findall
        self.specials = re.compile("(" + "|".join(map(re.escape, sorted(self.special, key=len, reverse=True))) + ")") if self.special else None
        self.size_of = {i: len(b) for i, b in self.bytes_of.items()}
        self.chunks = Remembered(self._chunk)
        self.pieces = Remembered(self._piece)

    def merge(self, data: bytes) -> list[int]:
        """The definition: repeatedly merge the pair of lowest rank, leftmost first."""
        parts = [data[k : k + 1] for k in range(len(data))]
        while len(parts) > 1:
            ranks = [self.rank.get(p, 1 << 60) for p in zip(parts, parts[1:])]
            low = min(ranks)
            if low == 1 << 60:
                break
            k, merged = 0, []
            while k < len(parts):
                if k + 1 < len(parts) and self.rank.get((parts[k], parts[k + 1])) == low:
                    merged.append(parts[k] + parts[k + 1])
                    k += 2
                else:
                    merged.append(parts[k])
                    k += 1
            parts = merged
        return [self.id_of[p] for p in parts]

    def compatible(self, a: int, b: int) -> bool:
        found = self.pairs.get((a, b))
        if found is None:
            if len(self.pairs) >= MOST_PAIRS:
                self.pairs.clear()
            found = self.pairs[a, b] = self._stays_apart(a, b)
        return found

    def _stays_apart(self, a: int, b: int) -> bool:
        """Whether merging the joined bytes of two tokens ends in just these two.

        Their merges are undone from the seam outwards, the later one first.  At each step the two
        parts that face each other across the seam must not have a merge of their own that comes
        before the one just undone, for it would have crossed the seam.
        """
        rank, halves, joins = self.made_at, self.halves, self.joins
        undone, by_left = len(self.rank), False
        while True:
            joined = joins.get((a, b))
            # on equal rank the leftmost pair merges first: the left token's own pair, but the seam before the right one's
            if joined is not None and (joined < undone or joined == undone and not by_left):
                return False
            x, y = rank.get(a, -1), rank.get(b, -1)
            if x < 0 and y < 0:
                return True
            if x > y:
                undone, by_left, a = x, True, halves[a][1]
            else:
                undone, by_left, b = y, False, halves[b][0]

    def prefix_token(self, token: int) -> int | None:
        """The longest token that is a proper prefix of this one."""
        if token not in self.shorter:
            text = self.bytes_of[token].decode("latin-1")
            self.shorter[token] = next((self.automaton.get(text[:k])[0] for k in range(len(text) - 1, 0, -1) if text[:k] in self.automaton), None)
        return self.shorter[token]

    def encode_piece(self, data: bytes) -> list[int]:
        text, compatible = data.decode("latin-1"), self.compatible
        # mostly every longest match stands beside the one before it, and the walk below would take just these
        out: list[int] = []
        at, last = 0, -1
        for end, (token, size) in self.automaton.iter_long(text):
            if end + 1 != at + size or last >= 0 and not compatible(last, token):
                break
            out.append(token)
            at, last = end + 1, token
        return out if at == len(data) else self._walk(text)

    def _walk(self, text: str) -> list[int]:
        n, sizes, compatible = len(text), self.size_of, self.compatible
        longest: list[int | None] = [None] * n
        for end, (token, size) in self.automaton.iter(text):
            longest[end + 1 - size] = token  # of one start, later ends are longer
        dead = bytearray(n + 1)
        out: list[int] = []
        at, token = 0, longest[0]
        while at < n:
            while token is not None:
                end = at + sizes[token]
                if not dead[end] and (not out or compatible(out[-1], token)):
                    break
                token = self.prefix_token(token)
            if token is None:
                dead[at] = 1
                last = out.pop()
                at -= sizes[last]
                token = self.prefix_token(last)
                continue
            out.append(token)
            at = end
            token = longest[at] if at < n else None
        return out

    def _piece(self, piece: str) -> bytes:
        return array.array("i", self.encode_piece(piece.encode("utf-8", "replace"))).tobytes()

    def _chunk(self, chunk: str) -> bytes:
        parts = self.split(chunk)
        return self.pieces[chunk] if len(parts) == 1 else b"".join(map(self.pieces.__getitem__, parts))

    def _plain(self, text: str) -> bytes:
        chunks = self.split(text) if _OTHER_WS.search(text) else _CHUNK.findall(text)
        return b"".join(map(self.chunks.__getitem__, chunks))

    def forget(self) -> None:
        """Drop what is remembered, at the end of a task; idle workers keep the vocabulary only."""
        for known in (self.chunks, self.pieces):
            known.clear()
            known.old = {}
        self.pairs.clear()
        release()

    def encode(self, text: str | None) -> bytes:
        """Ids as little-endian 32-bit bytes."""
        if not text:
            return b""
        if self.specials is None or not self.specials.search(text):
            return self._plain(text)
        return b"".join(np.array([self.special[p]], "<i4").tobytes() if p in self.special else self._plain(p) for p in self.specials.split(text) if p)


@functools.lru_cache(2)
def model(path: str) -> BacktrackingBpe:
    return BacktrackingBpe(path)


@functools.lru_cache(2)
def vocabulary(path: str) -> Vocabulary:
    return Vocabulary(path)


def _slices(b: pa.RecordBatch, weights) -> list[tuple[int, int]]:
    """Row ranges of a batch whose weights sum to a bounded amount."""
    out, at, held = [], 0, 0
    for k, w in enumerate(weights):
        held += w
        if held >= BATCH_IDS:
            out.append((at, k + 1))
            at, held = k + 1, 0
    if at < b.num_rows:
        out.append((at, b.num_rows))
    return out


def _encode_batches(path: str, text: str, ids: str):
    def run(batches):
        bpe = model(path)
        for b in batches:
            column = b.column(text)
            for x, y in _slices(b, pc.fill_null(pc.binary_length(column), 0).to_pylist()):
                data = [bpe.encode(t.as_py()) for t in column.slice(x, y - x)]
                offsets = np.concatenate(([0], np.cumsum([len(d) // 4 for d in data]))).astype(np.int32)
                lists = pa.ListArray.from_arrays(pa.array(offsets), pa.array(np.frombuffer(b"".join(data), "<i4"), pa.int32()))
                yield pa.RecordBatch.from_arrays([*b.slice(x, y - x).columns, lists], names=[*b.schema.names, ids])
        bpe.forget()

    return run


def _decode_batches(path: str, ids: str, text: str, tokens=None):
    def run(batches):
        words = (tokens or vocabulary)(path)
        for b in batches:
            column = b.column(ids)
            for x, y in _slices(b, np.diff(column.offsets.to_numpy()).tolist() if b.num_rows else []):
                part = column.slice(x, y - x)
                offsets, values = part.offsets.to_numpy(), part.values.to_numpy(zero_copy_only=False)
                texts = [words.decode(values[p:q]).decode("utf-8", "replace") for p, q in zip(offsets[:-1].tolist(), offsets[1:].tolist())]
                yield pa.RecordBatch.from_arrays([*b.slice(x, y - x).columns, pa.array(texts, pa.string())], names=[*b.schema.names, text])

    return run


def _both_batches(path: str, text: str, ids: str, decoded: str):
    """Encodes and decodes in one worker."""

    def run(batches):
        back = _decode_batches(path, ids, decoded, model)
        for b in _encode_batches(path, text, ids)(batches):
            yield from back([b])

    return run


def _fields(df: DataFrame) -> str:
    return ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in df.schema)


def encode(df: DataFrame, tokenizer: str, text: str = "text", ids: str = "ids") -> DataFrame:
    """``df`` with an array column of token ids."""
    return df.mapInArrow(_encode_batches(tokenizer, text, ids), f"{_fields(df)}, `{ids}` array<int>")


def decode(df: DataFrame, tokenizer: str, ids: str = "ids", text: str = "decoded") -> DataFrame:
    """``df`` with the text of a column of token ids; bytes that are no UTF-8 become U+FFFD."""
    return df.mapInArrow(_decode_batches(tokenizer, ids, text), f"{_fields(df)}, `{text}` string")


def round_trip(df: DataFrame, tokenizer: str, text: str = "text", ids: str = "ids", decoded: str = "decoded") -> DataFrame:
    """:func:`encode`, then :func:`decode`, in one pass over the rows."""
    return df.mapInArrow(_both_batches(tokenizer, text, ids, decoded), f"{_fields(df)}, `{ids}` array<int>, `{decoded}` string")


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    import public_tokenizers

    path = public_tokenizers.path("byte_bpe_50k.json")
    docs = documents(spark, sf_dir).select("doc_id", "text")
    return round_trip(docs, path).select(
        "doc_id",
        F.size("ids").cast("long").alias("n_tokens"),
        F.sha2(F.array_join(F.col("ids").cast("array<string>"), ","), 256).alias("ids_sha256"),
        F.sha2("decoded", 256).alias("decoded_sha256"),
    )
