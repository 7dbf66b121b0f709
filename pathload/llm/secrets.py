"""Secret scan: fixed base patterns, and assignment-aware lexing of source and configuration text.

The lexer reads name-value pairs (quoted or bare names; `=`, `:`, `:=`, `=>`; quoted
literals, joined literals, names of earlier constants; markup like <name>value</name>),
carries literals through constants to the names they are assigned to, and scores
each literal by how sensitive its target's name is and how much it looks like a
key. Literals that reach the threshold are spans of kind `literal`, unless a base
span holds them already.

Contracts: a null text is empty; an empty text has no spans; each row is judged by
itself, so ties, repeated rows and other columns change nothing. Offsets are code
points, ends exclusive.
"""

from __future__ import annotations

import hashlib
import math
import re
from bisect import bisect_right
from collections import Counter
from collections.abc import Iterator
from functools import lru_cache
from itertools import accumulate

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, functions as F

from pathload.llm.common import table

# The base patterns and their least lengths.
_ASSIGN = re.compile(r"""(password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", re.I | re.A)
_ACCESS = re.compile(r"AKIA[A-Z0-9]+")
_HEX = re.compile(r"[0-9a-f]{24,}")
KINDS = ("assign", "access", "hex", "literal")

# Sensitive parts of names, with weights.
NAME_WEIGHT = {
    "password": 1.0, "passwd": 1.0, "passphrase": 1.0, "pwd": 0.9, "secret": 1.0, "token": 0.9, "apikey": 1.0, "accesskey": 1.0,
    "privatekey": 1.0, "secretkey": 1.0, "clientsecret": 1.0, "authkey": 0.9, "authtoken": 1.0, "bearer": 0.9, "credential": 0.9,
    "signingkey": 1.0, "encryptionkey": 1.0, "connectionstring": 0.7, "authorization": 0.8, "salt": 0.5, "auth": 0.5, "key": 0.4,
}
#: Names that hold a sensitive part by chance.
_CHANCE = re.compile(r"authors?(?!i[sz])|authentic(?!at)|key(?:word|board)s?|(?:mon|tur|don|hot|hoc|joc)key")
#: What every name of a base assignment holds.
_BASE_STEMS = re.compile("pass|secret|token|key", re.I | re.A)
#: Least scores under names of small weight, with a digit and without.
WEAK, WEAK_LETTERS = 0.75, 0.85
_DULL = re.compile(r"(?i)(?:x{3,}|\*{3,}|\.{3,}|<.*>|\$\{.*\}|\{\{.*\}\}|%\(.*\)s|changeme|change_me|example|placeholder|dummy|test|todo|none|null|true|false|undefined|your[_-].*|redacted.*)$", re.S)
_DULL_ENDS = re.compile(r"(?i)(?:<.*>|\$\{.*\}|\{\{.*\}\}|%\(.*\)s|your[_-].*|redacted.*)$", re.S)
_PEM = re.compile(r"-----BEGIN [A-Z0-9 ]*PRIVATE KEY")
_SENTENCE = re.compile(r"(?i)\b(?:pass(?:word|phrase|wd|code)?s?|enter|your|please|must|required|invalid|incorrect|forgot|reset)\b")
_PAIR = re.compile(
    r"""(?:(?P<q>["'`])(?P<quoted>[A-Za-z_$][\w.$ -]*+)(?P=q)|(?<![\w.$-])(?P<bare>[A-Za-z_$][\w.$-]*+))
        (?:\s*+:\s*+[A-Za-z_][\w.\[\]]*+(?=\s*+=[^=]))?
        [ \t]*+(?:=>|:=|:|=(?!=))[ \t]*+""",
    re.X | re.A,
)
_MARKUP = re.compile(r"<([A-Za-z_][\w.-]*+)>([^<>]++)</\1>", re.A)
_LITERAL = re.compile(r"""[rbuf]{0,2}(?:"((?:[^"\\\n]|\\.)*+)"|'((?:[^'\\\n]|\\.)*+)'|`([^`\n]*+)`)""", re.A)
_NAME = re.compile(r"[A-Za-z_$][\w.$]*(?![\w(\[])", re.A)
_PLAIN = re.compile(r"[^\s,;\"'`<>(){}\[\]#]{6,}+")
_JOIN = re.compile(r"[ \t]*+(?:\+|\.\.|\.|&)[ \t]*+")
#: Characters that a value keeps of its start and of its end.
EDGE = 64


@lru_cache(4096)
def name_score(name: str) -> float:
    flat = re.sub(r"[^a-z0-9]", "", name.lower())
    if re.search(r"(public|primary|foreign|sort|cache|partition)key", flat):
        return 0.0
    flat = _CHANCE.sub(" ", flat)
    return max((w for part, w in NAME_WEIGHT.items() if part in flat), default=0.0)


@lru_cache(4096)
def holds_phrase(name: str) -> bool:
    """Whether a value under the name may be words with spaces."""
    return bool(re.search("passphrase|password|passwd|pwd", re.sub(r"[^a-z0-9]", "", name.lower())))


class Value:
    """A literal, or literals joined: its characters' counts, its edges and its parts; joined text is never built.

    A leaf counts its characters when they are asked for; a joined value adds up its parts' counts.
    """

    __slots__ = ("text", "a", "b", "parts", "told", "size", "_counts", "head", "tail")

    def __init__(self, text: str, a: int, b: int, counts: dict[str, int] | None = None, parts: tuple[Value, Value] | None = None):
        self.text, self.a, self.b, self._counts, self.parts, self.told = text, a, b, counts, parts, False
        if parts is None:
            self.size, self.head, self.tail = b - a, text[a : min(b, a + EDGE)], text[max(a, b - EDGE) : b]
        else:
            x, y = parts
            self.size, self.head, self.tail = x.size + y.size, (x.head + y.head)[:EDGE] if x.size < EDGE else x.head, (x.tail + y.tail)[-EDGE:] if y.size < EDGE else y.tail

    @property
    def counts(self) -> dict[str, int]:
        todo = [self]
        while todo:
            v = todo[-1]
            if v._counts is not None:
                todo.pop()
            elif v.parts is None:
                v._counts = Counter(v.text[v.a : v.b])
            elif left := [p for p in v.parts if p._counts is None]:
                todo += left
            else:
                v._counts = dict(v.parts[0]._counts)
                for c, n in v.parts[1]._counts.items():
                    v._counts[c] = v._counts.get(c, 0) + n
        return self._counts

    def spans(self) -> Iterator[tuple[int, int]]:
        """Spans of the literals that were not told of before."""
        todo = [self]
        while todo:
            v = todo.pop()
            if v.told:
                continue
            v.told = True
            if v.parts is None:
                yield v.a, v.b
            else:
                todo += v.parts

    def edges(self) -> str:
        """The whole text up to twice EDGE; of a longer one its start and end."""
        return self.head if self.size <= EDGE else self.head + self.tail[-min(EDGE, self.size - EDGE) :]

    def score(self, phrase: bool = False) -> float:
        """0 to 1 by length, mix of character classes and entropy; placeholders have 0; text with spaces too, but for private keys and, if asked for, phrases."""
        edges, whole = self.edges(), self.size <= 2 * EDGE
        if self.size < 6 or (_DULL if whole else _DULL_ENDS).match(edges):
            return 0.0
        if _PEM.match(self.head.lstrip()):
            return 1.0
        counts = self.counts
        if not whole and len(counts) <= 2 and {c.lower() for c in counts} in ({"x"}, {"*"}, {"."}):
            return 0.0
        if " " in counts or "\n" in counts:
            inner = edges.strip()
            spaced = any(c in inner or (not whole and counts.get(c, 0) > edges.count(c)) for c in " \n")
            if spaced and (not phrase or _SENTENCE.search(edges)):
                return 0.0
        shares = [n / self.size for n in counts.values()]
        entropy = -sum(x * math.log2(x) for x in shares if x > 0)
        classes = sum((any("a" <= c <= "z" for c in counts), any("A" <= c <= "Z" for c in counts), any("0" <= c <= "9" for c in counts), any(not (c.isascii() and c.isalnum()) for c in counts)))
        return min(1.0, entropy / 4) * 0.5 + min(16, self.size) / 16 * 0.25 + min(1.0, (classes - 1) / 2) * 0.25


def literal_score(value: str, phrase: bool = False) -> float:
    return Value(value, 0, len(value)).score(phrase)


def sensitive(name: str, value: Value, threshold: float) -> bool:
    """Whether the value is a secret under the name; every weight can pass."""
    weight = name_score(name)
    if not weight:
        return False
    score = value.score(holds_phrase(name))
    if weight >= 0.9:
        return weight * score >= threshold
    weak = WEAK if weight >= threshold * 1.2 or any("0" <= c <= "9" for c in value.counts) or _PEM.match(value.head.lstrip()) else WEAK_LETTERS
    return score >= min(threshold * 1.2 / weight, max(weak, threshold))


class Runs:
    """Plain values: suffixes of runs of plain characters, each run scanned once."""

    def __init__(self, text: str):
        self.text, self.start, self.end, self.at, self.left = text, 0, 0, 0, None

    def value(self, pos: int) -> Value | None:
        if not self.start <= pos < self.end:
            m = _PLAIN.match(self.text, pos)
            if not m:
                return None
            self.start, self.end, self.at, self.left = pos, m.end(), pos, None
        if self.end - pos < 6:
            return None
        if self.end - pos <= 4096:
            return Value(self.text, pos, self.end)
        # A long run may have many values: counts go down from one to the next.
        if self.left is None:
            self.at, self.left = pos, Counter(self.text[pos : self.end])
        for c in self.text[self.at : pos]:
            self.left[c] -= 1
            if not self.left[c]:
                del self.left[c]
        self.at = pos
        return Value(self.text, pos, self.end, dict(self.left))


def assignments(text: str) -> Iterator[tuple[str, Value]]:
    """(name, value of the literals it gets), constants carried forward."""
    known: dict[str, Value] = {}
    plain = Runs(text)
    at = 0
    while pair := _PAIR.search(text, at):
        name = pair["quoted"] or pair["bare"]
        value, pos = None, pair.end()
        while True:
            if m := _LITERAL.match(text, pos):
                k = next(i for i in (1, 2, 3) if m[i] is not None)
                one, pos = Value(text, *m.span(k)), m.end()
            elif (m := _NAME.match(text, pos)) and m[0] in known:
                one, pos = known[m[0]], m.end()
            elif value is None and (one := plain.value(pos)):
                pos = one.b
            else:
                break
            value = one if value is None else Value(text, 0, 0, parts=(value, one))
            step = _JOIN.match(text, pos)
            if not step or not (_LITERAL.match(text, step.end()) or (m := _NAME.match(text, step.end())) and m[0] in known):
                break
            pos = step.end()
        if value is not None:
            known[name] = value
            yield name, value
        at = max(pair.end(), pos if value is not None and pos > pair.end() and text[pos - 1] in "\"'`" else pair.end())
    if "</" in text:
        for m in _MARKUP.finditer(text):
            yield m[1], Value(text, *m.span(2))


def find_spans(text: str, threshold: float = 0.55) -> list[tuple[int, int, int]]:
    """(start, end, index of kind) of all spans of a text, sorted."""
    out = []
    if "=" in text or ":" in text:
        out += [(*m.span(), 0) for m in _ASSIGN.finditer(text) if len(m[2]) >= 6] if _BASE_STEMS.search(text) else []
    if "AKIA" in text:
        out += [(*m.span(), 1) for m in _ACCESS.finditer(text) if len(m[0]) >= 20]
    out += [(*m.span(), 2) for m in _HEX.finditer(text)]
    if "=" in text or ":" in text or "</" in text:
        base = sorted(out)
        starts, ends = [x for x, _, _ in base], list(accumulate((y for _, y, _ in base), max))
        seen = set()
        for name, value in assignments(text):
            if not value.told and sensitive(name, value, threshold):
                for a, b in value.spans():
                    i = bisect_right(starts, a)
                    if a < b and (a, b) not in seen and not (i and ends[i - 1] >= b):
                        seen.add((a, b))
                        out.append((a, b, 3))
    return sorted(out, key=lambda s: (s[0], s[2], s[1]))


def joined(spans: list[tuple[int, int, int]]) -> str:
    return ",".join(f"{KINDS[k]}:{a}:{b}" for a, b, k in spans)


def scan_secrets(docs: DataFrame, threshold: float = 0.55, key: str = "doc_id", text: str = "text") -> DataFrame:
    """(key, spans array<struct<kind, start, end>>, redacted): all spans of each whole text, and the text with them replaced."""

    def scan(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        kind = pa.struct([("kind", pa.string()), ("start", pa.int32()), ("end", pa.int32())])
        for b in batches:
            for at in range(0, b.num_rows, 1024):
                part = b.slice(at, 1024)
                texts = [t.as_py() or "" for t in part.column(1)]
                found = [find_spans(t, threshold) for t in texts]
                spans = pa.array([[{"kind": KINDS[k], "start": a, "end": e} for a, e, k in s] for s in found], pa.list_(kind))
                clean = pa.array([redact(t, s) for t, s in zip(texts, found, strict=True)], pa.string())
                yield pa.RecordBatch.from_arrays([part.column(0), spans, clean], [key, "spans", "redacted"])

    kept = docs.select(key, text)
    return kept.mapInArrow(scan, f"`{key}` {kept.schema[key].dataType.simpleString()}, spans array<struct<kind:string,start:int,end:int>>, redacted string")


def with_redacted(docs: DataFrame, threshold: float = 0.55, text: str = "text") -> DataFrame:
    """All columns, the text with its secrets replaced by marks; a null text stays null."""
    at = docs.columns.index(text)

    def clean(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            texts = [t.as_py() for t in b.column(at)]
            new = pa.array([t if t is None else redact(t, find_spans(t, threshold)) for t in texts], pa.string())
            yield b.set_column(at, text, new)

    return docs.mapInArrow(clean, docs.schema)


def redact(text: str, spans: list[tuple[int, int, int]]) -> str:
    """The text with each union of overlapping spans replaced by one mark."""
    if not spans:
        return text
    out, at = [], 0
    for a, b, k in spans:
        if a >= at:
            out += [text[at:a], f"[{KINDS[k].upper()}]"]
        at = max(at, b)
    return "".join([*out, text[at:]])


def op2_secrets(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = scan_secrets(table(spark, sf_dir, "documents")).drop("redacted")
    text = lambda s: F.concat_ws(":", s["kind"], s["start"].cast("string"), s["end"].cast("string"))
    base = F.filter("spans", lambda s: s["kind"] != KINDS[3])
    count = lambda kind: F.size(F.filter("spans", lambda s: s["kind"] == kind)).cast("long")
    return found.select(
        "doc_id",
        count("assign").alias("n_assign"),
        count("access").alias("n_access"),
        count("hex").alias("n_hex"),
        F.sha2(F.array_join(F.transform(base, text), ","), 256).alias("base_sha256"),
        F.array_join(F.transform("spans", text), ",").alias("spans"),
    )


def span_digest(spans: list[tuple[int, int, int]]) -> str:
    return hashlib.sha256(joined([s for s in spans if s[2] < 3]).encode()).hexdigest()
