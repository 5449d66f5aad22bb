"""Best-fit packing: documents as token sequences into as few sequences of fixed length as possible.

Texts are tokenised where they are read; only (row, piece, start, length, checksum) go on. Pieces are dealt
into shards of bounded size by a hash of their document, and each shard is packed by best-two-fit over a
table of lengths: fill a sequence greedily with the longest piece that fits, then, if its smallest piece
can give way to two unpacked pieces that fill the widened gap more tightly, swap it for them. A shard leaves
one sequence partly empty at most beyond what its lengths force, so many shards cost little.

Where the swaps cost a shard a sequence in the end, as they can with few short pieces, the fill without them stands;
the column ``swapped`` says which it was.

Null text counts as empty: its document is the single end id. Repeated rows are packed each. An empty table
gives no rows. Very long texts are cut into pieces, never shortened. Only doc_id and the text are read, so other
columns never clash.
"""

from __future__ import annotations

import json
import re
import zlib
from collections.abc import Iterator
from pathlib import Path

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from componentry.llm.words import text_blocks
from componentry.plans.storage import cut

LENGTH = 2048
END_ID = 0
SHARD_PIECES = 60_000
CACHE = 500_000

PIECES = T.StructType(
    [T.StructField("doc_id", T.LongType()), T.StructField("piece", T.IntegerType()), T.StructField("start", T.LongType()), T.StructField("length", T.LongType()), T.StructField("ids_crc32", T.LongType()), T.StructField("row_key", T.LongType())]
)

def vocabulary_path(name: str = "word_bpe_49k.json") -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


#: a chunk of Latin letters, perhaps with a comma or full stop behind it
_SIMPLE = re.compile(r"([A-Za-z\u00c0-\u00d6\u00d8-\u00f6\u00f8-\u00ff]+)([.,]?)").fullmatch
#: a comma or full stop behind what is no letter, digit or space: part of a run of marks
_RUN = re.compile(r"[,.](?<=[^A-Za-z\u00c0-\u00d6\u00d8-\u00f6\u00f8-\u00ff0-9 \n][,.])").search
_END = b"\x01"


def _latin(text: str) -> bool:
    if text.isascii():
        return True
    try:
        text.encode("latin-1")
    except UnicodeEncodeError:
        return False
    return True


def chunks(text: str) -> list[str]:
    """Space separated chunks that the vocabulary encodes apart.

    In Latin-1 text letters can be lowered at once, and a comma or full stop behind a letter, digit or space
    starts a chunk, as it does in the vocabulary: so words and marks repeat, and few chunks are new. Texts with runs of
    marks, other letters or what may be a special token are cut at spaces only.
    """
    if "<|" not in text and _latin(text) and not _RUN(text):
        text = text.lower().replace(",", " ,").replace(".", " .")
    return text.replace("\n", " ").split(" ")


def _byte_letters() -> dict[str, int]:
    """The letters that byte-level vocabularies write bytes as: printable Latin-1 as itself, the rest from 256 on."""
    own = [*range(33, 127), *range(161, 173), *range(174, 256)]
    rest = [b for b in range(256) if b not in own]
    return {chr(b): b for b in own} | {chr(256 + k): b for k, b in enumerate(rest)}


class WordMerger:
    """Pair merging of lower-case words by the vocabulary's own merges, many words a call; the end of a word is a byte of its own."""

    def __init__(self, path: str):
        import tiktoken

        model = json.loads(Path(path).read_text())["model"]
        vocabulary, suffix, letters = model["vocab"], model["end_of_word_suffix"], _byte_letters()
        merged = ["".join(m if isinstance(m, list) else m.split(" ")) for m in model["merges"]]
        if not suffix or len(set(merged)) != len(merged):
            raise ValueError("this vocabulary's merges are not told apart by their results")
        pieces = [*letters, *(c + suffix for c in letters), *merged]

        def raw(piece: str) -> bytes:
            ends = piece.endswith(suffix)
            return bytes(letters[c] for c in piece.removesuffix(suffix)) + (_END if ends else b"")

        ranks: dict[bytes, int] = {}
        for p in pieces:
            ranks.setdefault(raw(p), len(ranks))
        self.ids = np.zeros(len(ranks), "<u4")
        self.ends = np.zeros(len(ranks), bool)
        for p in pieces:
            self.ids[ranks[raw(p)]], self.ends[ranks[raw(p)]] = vocabulary[p], p.endswith(suffix)
        self.encode = tiktoken.Encoding("words", pat_str="[^ ]+", mergeable_ranks=ranks, special_tokens={}).encode_ordinary

    def __call__(self, words: list[str]) -> list[bytes]:
        found = np.array(self.encode((_END.decode() + " ").join(words) + _END.decode()), np.int64)
        ends = (4 * (np.flatnonzero(self.ends[found]) + 1)).tolist()
        return list(map(self.ids[found].tobytes().__getitem__, map(slice, [0, *ends], ends)))


#: what must come out of the chunks as it does of the whole text: spaces, line ends, letters, marks, digits, special tokens
_PROBES = ("one two  three\nfour", " Lead and trail ", "It's the end, of all. Or not?", "Größe, façade. naïve ÉTÉ", "a1b2 3,4 5.6 x-y", "...,, #tag @name (in) [sq] {cu}", "日本 語, тест. 한글", "<|endoftext|> inside, here.", "tab\there\rback", "e\u0301 \u00a0 nbsp, \u2014 dash.")


class WordIds:
    """Ids of texts as little-endian 32-bit bytes, from a bounded cache of space separated chunks.

    The cache has two generations of at most ``cache`` chunks: when the young one is full it becomes the old one,
    and what is met again moves on, so frequent chunks are not encoded again. Most new chunks are a word of Latin letters
    with at most one mark behind: the vocabulary lowers the word, merges it apart from all else, and encodes the
    mark alone. Those words go through WordMerger; any other chunk goes through the whole tokeniser.
    """

    def __init__(self, path: str, cache: int = CACHE):
        import os

        os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")
        from tokenizers import Tokenizer

        self.tokenizer, self.limit, self.merge = Tokenizer.from_file(path), cache, WordMerger(path)
        self.known: dict[str, bytes] = {}
        self.old: dict[str, bytes] = {}
        self.marks = {m: np.array(self._ids(m), "<u4").tobytes() for m in ",."} | {"": b""}
        for probe in _PROBES:
            if self.encode([probe]) != [np.array(self._ids(probe), "<u4").tobytes()]:
                raise ValueError(f"this vocabulary does not encode chunks apart: {probe!r}")
        self.known, self.old = {}, {}

    def _ids(self, text: str) -> list[int]:
        return self.tokenizer.encode(text, add_special_tokens=False).ids

    def _learn(self, new: set[str]) -> None:
        known, old, marks = self.known, self.old, self.marks
        lower = [w for w in new if w.islower() and w.isalpha() and (w.isascii() or _latin(w))]
        forms = [(w, m[1].lower(), m[2]) for w in new.difference(lower) if (m := _SIMPLE(w))]
        words = {c for _, c, _ in forms}.difference(known)
        again = words & old.keys()
        known.update((c, old[c]) for c in again)
        lack = list((words - again).union(lower))
        for at in range(0, len(lack), 5000):
            part = lack[at : at + 5000]
            known.update(zip(part, self.merge(part), strict=True))
        known.update([(w, known[c] + marks[m]) for w, c, m in forms])
        rest = [w for w in new if w not in known]
        if rest:
            made = self.tokenizer.encode_batch_fast(rest, add_special_tokens=False)
            known.update((w, np.array(e.ids, "<u4").tobytes()) for w, e in zip(rest, made, strict=True))

    def encode(self, texts: list[str]) -> list[bytes]:
        split = [chunks(t) for t in texts]
        if len(self.known) > self.limit:
            self.known, self.old = {}, self.known
        new = set().union(*split).difference(self.known)
        if new:
            again = new & self.old.keys()
            self.known.update((w, self.old[w]) for w in again)
            self._learn(new - again)
        get = self.known.__getitem__
        return [b"".join(map(get, x)) for x in split]


_encoders: dict[str, WordIds] = {}


def document_pieces(docs: DataFrame, path: str | None = None, *, length: int = LENGTH, end_id: int = END_ID, text: str = "text") -> DataFrame:
    """Pieces of every row of ``docs``: longer documents are cut each ``length`` ids, the last piece may be shorter."""
    path = path or vocabulary_path()
    end = int(end_id).to_bytes(4, "little")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        if path not in _encoders:
            _encoders[path] = WordIds(path)
        encoder = _encoders[path]
        for batch in batches:
            for a, b in text_blocks(batch, "_text", 1 << 20):
                part = batch.slice(a, b - a)
                rows = []
                for doc, key, ids in zip(part["doc_id"].to_pylist(), part["row_key"].to_pylist(), encoder.encode([t or "" for t in part["_text"].to_pylist()]), strict=True):
                    ids += end
                    for k, at in enumerate(range(0, len(ids), 4 * length)):
                        piece = ids[at : at + 4 * length]
                        rows.append((doc, k, at // 4, len(piece) // 4, zlib.crc32(piece), key))
                if rows:
                    yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows, strict=True), (pa.int64(), pa.int32(), pa.int64(), pa.int64(), pa.int64(), pa.int64()), strict=True)], names=PIECES.names)

    keyed = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.xxhash64("doc_id", F.length(text)).alias("row_key"), F.col(text).alias("_text"))
    return keyed.mapInArrow(run, PIECES)


def _fill(count: list[int], size: int, swap: bool) -> list[list[int]]:
    """Bins of lengths: each filled with the longest that fits; with ``swap`` its last piece may give way to two."""
    count = list(count)
    present = 0  # bit n: a piece of length n is left
    for n in range(1, size + 1):
        if count[n]:
            present |= 1 << n

    def longest(most: int) -> int:
        return (present & ((1 << (most + 1)) - 1)).bit_length() - 1 if most > 0 else 0

    bins: list[list[int]] = []
    while present:
        own, gap = [], size
        while (n := longest(gap)) > 0:
            own.append(n)
            gap -= n
            count[n] -= 1
            if not count[n]:
                present &= ~(1 << n)
        if swap and gap and present and len(own) > 1:
            least = own[-1]
            room = gap + least
            best, pair = least, None
            first = longest(room - 1)
            while first > 0 and first * 2 >= best:
                second = longest(min(room - first, first if count[first] > 1 else first - 1))
                if second > 0 and best < first + second:
                    best, pair = first + second, (first, second)
                    if best == room:
                        break
                first = longest(first - 1)
            if pair:
                own.pop()
                count[least] += 1
                present |= 1 << least
                for n in pair:
                    own.append(n)
                    count[n] -= 1
                    if not count[n]:
                        present &= ~(1 << n)
        bins.append(own)
    return bins


def best_two_fit(lengths: np.ndarray, size: int = LENGTH) -> tuple[np.ndarray, np.ndarray, bool]:
    """(bin, offset) of each length, and whether the fill with swaps stands. Works on counts per length, so equal pieces are interchangeable."""
    count = [0] * (size + 1)
    for n, c in zip(*np.unique(lengths, return_counts=True), strict=True):
        count[n] = int(c)
    swapped, plain = _fill(count, size, True), _fill(count, size, False)
    better = len(swapped) <= len(plain)
    bins = swapped if better else plain
    # hand the places out to the pieces of each length
    places: dict[int, list[tuple[int, int]]] = {}
    for b, own in enumerate(bins):
        at = 0
        for n in own:
            places.setdefault(n, []).append((b, at))
            at += n
    taken = {n: iter(x) for n, x in places.items()}
    out = np.array([next(taken[n]) for n in lengths.tolist()], np.int64).reshape(-1, 2)
    return out[:, 0], out[:, 1], better


def pack(pieces: DataFrame, *, length: int = LENGTH, shard_pieces: int = SHARD_PIECES) -> DataFrame:
    """``pieces`` with sequence_id, offset and swapped. ``pieces`` is counted here: pass a cut."""
    n = pieces.count()
    shards = max(1, -(-n // shard_pieces))
    dealt = pieces.withColumn("_shard", F.pmod(F.xxhash64("row_key", "piece"), F.lit(shards)).cast("int"))
    schema = T.StructType([*PIECES.fields[:-1], T.StructField("sequence_id", T.LongType()), T.StructField("offset", T.LongType()), T.StructField("swapped", T.BooleanType())])

    def run(key: tuple, rows: pd.DataFrame) -> pd.DataFrame:
        rows = rows.sort_values(["doc_id", "row_key", "ids_crc32", "piece"], kind="stable")
        bins, at, swapped = best_two_fit(rows["length"].to_numpy(), length)
        return pd.DataFrame({**{c: rows[c] for c in PIECES.names[:-1]}, "sequence_id": (int(key[0]) << 32) + bins, "offset": at, "swapped": swapped})

    return dealt.groupBy("_shard").applyInPandas(run, schema)


def pack_documents(docs: DataFrame) -> DataFrame:
    return pack(cut(document_pieces(docs), "pieces"))


def op6_best_fit_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pack_documents(spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text"))
