"""Secret scans: patterns, and dictionary-primed compression that finds strings no dictionary explains.

A candidate is a quoted or unspaced run of 12 characters or more, of any kind, that shares a line with a word that names
something sensitive, on either side within ``NEAR`` characters (or begins the line after one that ends with such a
word). Its marginal cost is the compressed size of its surroundings with it, less that without it, by a zstandard
compressor primed with a dictionary of code and identifier words. The surroundings, up to ``AROUND`` characters on
either side without the candidate's own copies, are the dictionary of this document: identifiers and words that it
uses cost little beside them; random keys cost their own entropy. The dictionary stands at the head of what is
compressed, so that it serves for matches and its letters set the entropy coder even where surroundings are short.
Candidates at ``NOVEL`` bytes a byte or more are reported as kind ``novel``, unless they overlap a pattern's span,
which always stays. Nothing but the compressed size decides on a candidate.

Null text counts as empty. Spans are in code points, end exclusive, over whole texts, however long; an empty text has
none. Repeated rows are scanned each; an empty table gives no rows. Only the columns named in ``keep`` travel along.
"""

from __future__ import annotations

import hashlib
import re

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import types as T

from componentry.llm.words import text_map

# fixed values: the patterns and the least lengths of what they find
ASSIGN = re.compile(r"""(password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", re.ASCII | re.IGNORECASE)
ACCESS = re.compile(r"AKIA[A-Z0-9]+")
HEX = re.compile(r"[0-9a-f]{16,}")  # a run under 16 characters fails, and a run has no other start
KINDS = ("assign", "access", "hex", "novel")

SENSITIVE = re.compile(r"secret|token|passw|passphrase|pwd|api.?key|private.?key|signing.?key|encryption.?key|access.?key|credential|bearer|authorization|client.?id|connection.?string", re.ASCII | re.IGNORECASE)
RUN = re.compile(r"""[^\s"'`]{12,}""")
#: a sensitive name and the sign that gives it a value, at the start of a run
_NAMED = re.compile(rf"[\w.-]*?(?:{SENSITIVE.pattern})[\w.-]*[=:]+", re.ASCII | re.IGNORECASE)
_HANGS = re.compile(r"""[\s"'`=:>(\[{-]*""").fullmatch
LEAST = 12
NEAR = 200
AROUND = 2048
LEVEL = 9
NOVEL = 0.85

_IDENTIFIERS = (
    "import return function class const public private static void string int float double boolean true false null none self this new "
    "for while if else elif switch case break continue try catch except finally raise throw async await lambda yield def var let type "
    "interface struct enum package namespace include define user username name email address client server request response header "
    "authorization bearer token access refresh session cookie secret password passwd credential private key public_key api_key api "
    "config configuration settings environment production development test database connection host port url path file directory "
    "http https www com org net index value values list map dict array object key id uuid version release license copyright author "
    "get set put post delete update create insert select from where order group by limit offset join left right inner outer and or not "
    "the of and to in is that it was for on are with as his they be at one have this"
)


class Novelty:
    """Marginal compressed bytes beside one dictionary of words."""

    def __init__(self, identifiers: str = _IDENTIFIERS, level: int = LEVEL):
        import zstandard

        self.prime = " ".join(sorted(set(identifiers.split()))).encode()
        self.compress = zstandard.ZstdCompressor(level=level, write_content_size=False, write_checksum=False).compress

    def rate(self, text: str, start: int, end: int) -> float:
        """Marginal compressed bytes a byte of ``text[start:end]`` beside its surroundings."""
        word = text[start:end]
        around = (text[max(0, start - AROUND) : start] + "\n" + text[end : end + AROUND] + "\n").replace(word, "")
        around, own = self.prime + around.encode("utf-8", "surrogatepass"), word.encode("utf-8", "surrogatepass")
        return (len(self.compress(around + own)) - len(self.compress(around))) / len(own)


def base_spans(text: str) -> list[tuple[int, int, str]]:
    """(start, end, kind) of the pattern matches that are long enough; matches do not overlap within a kind."""
    out = [(m.start(), m.end(), "assign") for m in ASSIGN.finditer(text) if len(m[2]) >= 12]
    if "AKIA" in text:
        out += [(m.start(), m.end(), "access") for m in ACCESS.finditer(text) if m.end() - m.start() >= 18]
    out += [(m.start(), m.end(), "hex") for m in HEX.finditer(text)]
    return sorted(out, key=lambda s: (s[0], KINDS.index(s[2])))


def sensitive_stretches(text: str) -> list[tuple[int, int]]:
    """Stretches of lines around the sensitive words, merged, that cut no run in two."""
    out: list[tuple[int, int]] = []
    for m in SENSITIVE.finditer(text):
        line, end = text.rfind("\n", 0, m.start()) + 1, text.find("\n", m.end())
        end = len(text) if end < 0 else end
        if m.end() + NEAR >= end and _HANGS(text, m.end(), end):  # the value stands on the next line
            end = text.find("\n", end + 1)
            end = len(text) if end < 0 else end
        a, b = max(line, m.start() - NEAR), min(end, m.end() + NEAR)
        while a > line and not text[a - 1].isspace():
            a -= 1
        while b < end and not text[b].isspace():
            b += 1
        if out and a <= out[-1][1]:
            out[-1] = (out[-1][0], max(b, out[-1][1]))
        else:
            out.append((a, b))
    return out


def candidates(text: str) -> list[tuple[int, int]]:
    """Runs in sensitive stretches: what stands between quotes as it is, else without the marks around it and a name before ``=`` or ``:``."""
    out = []
    for low, high in sensitive_stretches(text):
        for m in RUN.finditer(text, low, high):
            a, b = m.span()
            named = _NAMED.match(text, a, b)
            a = named.end() if named else a
            if not (a > 0 and b < len(text) and text[a - 1] in "\"'`" and text[b] == text[a - 1]):
                while a < b and text[a] in "([{<":
                    a += 1
                while a < b and text[b - 1] in ".,;:!?)]}>":
                    b -= 1
            if b - a >= LEAST:
                out.append((a, b))
    return out


def novel_spans(text: str, base: list[tuple[int, int, str]], novelty: Novelty) -> list[tuple[int, int, str]]:
    free = [(a, b) for a, b in candidates(text) if not any(a < e and s < b for s, e, _ in base)]
    return [(a, b, "novel") for a, b in free if novelty.rate(text, a, b) >= NOVEL]


def joined(spans: list[tuple[int, int, str]]) -> str:
    return ",".join(f"{k}:{a}:{b}" for a, b, k in sorted(spans, key=lambda s: (s[0], KINDS.index(s[2]))))


def secret_scan(docs: DataFrame, *, keep: list[str] | None = None, text: str = "text", identifiers: str = _IDENTIFIERS) -> DataFrame:
    """``keep`` columns, counts by kind, the digest of the pattern spans and all spans with the method's."""
    fields = [T.StructField(n, T.LongType()) for n in ("n_assign", "n_access", "n_hex", "n_novel")] + [T.StructField(n, T.StringType()) for n in ("base_sha256", "spans")]

    def run(texts: pa.Array) -> list[pa.Array]:
        novelty = Novelty(identifiers)
        rows = []
        for t in texts.to_pylist():
            t = t or ""
            base = base_spans(t)
            more = novel_spans(t, base, novelty)
            kinds = [k for _, _, k in base]
            rows.append((*(kinds.count(k) for k in KINDS[:3]), len(more), hashlib.sha256(joined(base).encode()).hexdigest(), joined(base + more)))
        cols = list(zip(*rows, strict=True)) or [()] * 6
        return [pa.array(c, pa.int64() if i < 4 else pa.string()) for i, c in enumerate(cols)]

    return text_map(docs, text, keep if keep is not None else ["doc_id"], fields, run)


def op5_secret_scans(spark: SparkSession, sf_dir: str) -> DataFrame:
    return secret_scan(spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text"))
