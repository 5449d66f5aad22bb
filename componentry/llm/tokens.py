"""Token counts: exact counts at every prefix by dynamic programming, so budgets need no second encoding.

In the vocabulary used no piece has the space mark after another character, and none has a line feed; nor has any a
letter with, say, a comma behind it: which signs never follow a letter is read from the vocabulary. No token crosses
the start of a run of spaces, a line feed or the end of a word before such a sign, so a text is a sequence of segments
that are encoded alone: count(prefix) = count(segments before) + count(part of the segment). A segment has a
table over its prefixes, filled by extending shorter prefixes by one last token; the tables of a text's segments
are stored in a row, as steps from one prefix to the next, and every count is a running sum of them.

Null text counts as empty; an empty text has no tokens. Control strings such as ``<s>`` in a text are
ordinary characters, as in the library's default. Repeated rows are counted each; an empty table gives no rows.
Very long texts have one table each, held whole. Only the columns named in ``keep`` travel along.
"""

from __future__ import annotations

import re
from array import array
from operator import sub

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from componentry.llm.words import text_map
from componentry.plans.storage import cut

MARK = "▁"
LETTERS = "A-Za-z\u00c0-\u00d6\u00d8-\u00f6\u00f8-\u00ff"
LIMIT = 4096
CACHE = 400_000
#: prefixes of up to so many characters are kept for the segments that share them
SHARED = 16
_SHORT = (3, 2, 1)


def vocabulary_path(name: str = "piece_bpe_32k.model") -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


class PrefixCounter:
    """Counts of one vocabulary, by tables of segments kept in a bounded cache of two generations."""

    def __init__(self, path: str, cache: int = CACHE):
        import sentencepiece

        self.sp = sentencepiece.SentencePieceProcessor(model_file=path)
        sp = self.sp
        plain = [i for i in range(sp.get_piece_size()) if not (sp.is_control(i) or sp.is_unknown(i) or sp.is_byte(i) or sp.is_unused(i))]
        self.score = {sp.id_to_piece(i): sp.get_score(i) for i in plain}
        if any(MARK in p.lstrip(MARK) or "\n" in p for p in self.score):
            raise ValueError("pieces of this vocabulary cross segment starts")
        letter = re.compile(f"[{LETTERS}]").fullmatch
        follow = {b for p in self.score for a, b in zip(p, p[1:], strict=False) if letter(a)}
        ends = "".join(re.escape(c) for c in map(chr, range(33, 127)) if not letter(c) and c not in follow)
        # spaces, other signs, letters; signs that may follow a letter go on, those that never do start anew
        other = f"[^ {MARK}\\n{LETTERS}]*[{LETTERS}]*"
        self.segment = re.compile(f"\\n|(?=.)[ {MARK}]*{other}(?:[^ {MARK}\\n{LETTERS}{ends}]{other})*")
        self.limit = cache
        self.steps, self.older_steps = {}, {}
        self._splits: dict[str, tuple[int, bool] | None] = {}
        self._joins: dict[tuple[str, str], bool] = {}
        self._heads: dict[str, bytes] = {}
        self.whole = frozenset(p for p in self.score if self._split(p) is not None)
        # lengths that a last token can have, longest first, by the last four characters
        found: dict[str, set[int]] = {}
        for p in self.whole:
            if len(p) > 3:
                found.setdefault(p[-4:], set()).add(len(p))
        self._ends = {g: (*sorted(x, reverse=True), *_SHORT) for g, x in found.items()}

    def segments(self, text: str) -> list[str]:
        """Segments in order; the library puts one space before a text."""
        return self.segment.findall(" " + text) if text else []

    def prefix_steps(self, text: str) -> bytes:
        """The stored table of a text: by how much each character of it, and of the space put before it, changes the count."""
        if len(self.steps) > self.limit:  # the young generation is full: it becomes the old one
            self.steps, self.older_steps = {}, self.steps
        known, older = self.steps, self.older_steps
        segs = self.segments(text)
        for s in set(segs).difference(known):
            known[s] = older.get(s) or self._steps(s)
        return b"".join([known[s] for s in segs])

    def _steps(self, segment: str) -> bytes:
        n = self.table(segment)
        return array("h", map(sub, n[1:], n)).tobytes()

    # -- within a segment

    def _merge(self, parts: list[str]) -> list[str]:
        """Pair merging: the best scored neighbour pair first, the leftmost of equals."""
        return self._merged(parts)[0]

    def _merged(self, parts: list[str]) -> tuple[list[str], int, bool]:
        """The merged parts, the length of the left side of the last merge, and whether scores only fell on the way."""
        parts, left, falling, before = list(parts), 0, True, None
        while len(parts) > 1:
            best, at = None, -1
            for i in range(len(parts) - 1):
                s = self.score.get(parts[i] + parts[i + 1])
                if s is not None and (best is None or s > best):
                    best, at = s, i
            if best is None:
                break
            falling &= before is None or best <= before
            before, left = best, len(parts[at])
            parts[at : at + 2] = [parts[at] + parts[at + 1]]
        return parts, left, falling

    def _split(self, piece: str) -> tuple[int, bool] | None:
        """Where the last merge of a piece joined it and whether scores only fell; None if its characters merge to something else."""
        if piece not in self._splits:
            parts, left, falling = self._merged(list(piece))
            self._splits[piece] = (left, falling) if len(parts) == 1 else None
        return self._splits[piece]

    def _joined(self, a: str, b: str) -> bool:
        """Whether the tokens a, b stay as they are side by side."""
        hit = self._joins.get((a, b))
        if hit is None:
            if len(self._joins) > self.limit:
                self._joins.clear()
            falling = all(len(x) == 1 or self._split(x)[1] for x in (a, b))
            hit = self._joins[a, b] = self._stay(a, b) if falling else self._merge([*a, *b]) == [a, b]
        return hit

    def _stay(self, a: str, b: str) -> bool:
        """The same for tokens made by merges of falling score: the merges next to the border are taken back, latest first,
        and at no time may a merge across the border have been due before the one taken back."""
        score = self.score
        if a + b in score:
            return False
        while len(a) > 1 or len(b) > 1:
            if len(b) == 1 or (len(a) > 1 and score[a] < score[b]):
                due, a = score[a], a[self._split(a)[0] :]
                across = score.get(a + b)
                if across is not None and across > due:
                    return False
            else:
                due, b = score[b], b[: self._split(b)[0]]
                across = score.get(a + b)
                if across is not None and across >= due:
                    return False
        return True

    def _width(self, piece: str) -> int:
        """Tokens of a piece: unknown characters fall back to bytes."""
        return 1 if piece in self.score else len(piece.encode("utf-8", "surrogatepass"))

    def table(self, segment: str) -> list[int]:
        """Tokens of every prefix of ``segment`` (0 to its length): each prefix is a shorter one and one last token.

        Segments that begin alike share the lengths of last tokens and the counts of their common prefixes.
        """
        s = segment.replace(" ", MARK)
        heads, score, whole, ends, joins = self._heads, self.score, self.whole, self._ends, self._joins
        n = len(s)
        k = min(n, SHARED)
        while k and (kept := heads.get(s[:k])) is None:
            k -= 1
        if k:
            widths, counts = list(kept[: k + 1]), list(kept[k + 1 :])
        else:
            widths, counts = [0], [0]
        for i in range(k + 1, n + 1):
            for width in ends.get(s[i - 4 : i], _SHORT) if i > 3 else _SHORT:
                j = i - width
                if j < 0:
                    continue
                piece = s[j:i]
                if width > 1 and piece not in whole:
                    continue
                if not j:
                    break
                before = s[j - widths[j] : j]
                hit = joins.get((before, piece))
                if self._joined(before, piece) if hit is None else hit:
                    break
            widths.append(i - j)
            counts.append(counts[j] + (1 if piece in score else self._width(piece)))
            if i <= SHARED:
                heads[s[:i]] = bytes(widths + counts)
        if len(heads) > self.limit:
            heads.clear()
        return counts

    def count_at(self, text: str, chars: int) -> int:
        """Tokens of the first ``chars`` characters of ``text``."""
        return count_at(self.prefix_steps(text), chars)

    def cut_at(self, text: str, budget: int) -> int:
        """The most leading characters of ``text`` whose count is within ``budget`` tokens."""
        return cut_at(self.prefix_steps(text), budget)


def prefix_counts(stored: bytes) -> np.ndarray:
    """Tokens of every prefix (0 characters to all) from the stored table of a text."""
    out = np.cumsum(np.frombuffer(stored, np.int16), dtype=np.int64)
    if not len(out):
        return np.zeros(1, np.int64)
    out[0] = 0  # the space put before a text counts only with what follows
    return out


def count_at(stored: bytes, chars: int) -> int:
    """Tokens of the first ``chars`` characters, read from the stored table."""
    n = prefix_counts(stored)
    return int(n[min(max(chars, 0), len(n) - 1)])


def cut_at(stored: bytes, budget: int) -> int:
    """The most leading characters whose count is within ``budget`` tokens, read from the stored table."""
    fit = np.flatnonzero(prefix_counts(stored) <= budget)
    return int(fit[-1]) if len(fit) else 0


_counters: dict[str, PrefixCounter] = {}


def counter(path: str) -> PrefixCounter:
    """One counter per vocabulary and process."""
    if path not in _counters:
        _counters[path] = PrefixCounter(path)
    return _counters[path]


def prefix_tables(docs: DataFrame, path: str | None = None, *, keep: list[str] | None = None, text: str = "text") -> DataFrame:
    """``keep`` columns with n_bytes and prefix_steps, the table that ``count_at`` and ``cut_at`` read: two bytes a character, few distinct ones."""
    path = path or vocabulary_path()
    fields = [T.StructField("n_bytes", T.LongType()), T.StructField("prefix_steps", T.BinaryType())]

    def run(texts: pa.Array) -> list[pa.Array]:
        c = counter(path)
        sizes = pc.fill_null(pc.binary_length(texts.cast(pa.binary())), 0).cast(pa.int64())
        return [sizes, pa.array([c.prefix_steps(t or "") for t in texts.to_pylist()], pa.binary())]

    return text_map(docs, text, keep if keep is not None else ["doc_id"], fields, run, most=1 << 20)


def token_counts(docs: DataFrame, path: str | None = None, *, keep: list[str] | None = None, limit: int = LIMIT, text: str = "text", prefixes: bool = False) -> DataFrame:
    """``keep`` columns with what stored tables say: n_bytes, n_tokens and over_limit (the last entry), limit_chars (the most leading
    characters within ``limit`` tokens); with ``prefixes`` also the array prefix_tokens, entry k for the first k characters."""
    keep = keep if keep is not None else ["doc_id"]
    stored = cut(prefix_tables(docs, path, keep=keep, text=text), "prefixes")
    fields = [T.StructField("n_tokens", T.LongType()), T.StructField("over_limit", T.BooleanType()), T.StructField("limit_chars", T.LongType())]
    if prefixes:
        fields.append(T.StructField("prefix_tokens", T.ArrayType(T.LongType())))

    def run(tables: pa.Array) -> list[pa.Array]:
        every = [prefix_counts(t.as_buffer()) for t in tables]
        n = [int(x[-1]) for x in every]
        fit = [len(x) - 1 if k <= limit else int(np.flatnonzero(x <= limit)[-1]) for x, k in zip(every, n, strict=True)]
        out = [pa.array(n, pa.int64()), pa.array([x > limit for x in n], pa.bool_()), pa.array(fit, pa.int64())]
        return out + ([pa.array(every, pa.list_(pa.int64()))] if prefixes else [])

    return text_map(stored, "prefix_steps", [*keep, "n_bytes"], fields, run, most=2 << 20)


def truncate(docs: DataFrame, budget: int, path: str | None = None, text: str = "text") -> DataFrame:
    """doc_id and the text cut to ``budget`` tokens."""
    path = path or vocabulary_path()

    def run(texts: pa.Array) -> list[pa.Array]:
        c = counter(path)
        return [pa.array([None if t is None else t[: c.cut_at(t, budget)] for t in texts.to_pylist()], pa.string())]

    return text_map(docs, text, ["doc_id"], [T.StructField("text", T.StringType())], run, most=1 << 20)


def op9_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    return token_counts(docs.select("doc_id", F.col("text")))
