"""Byte-level BPE by a backtracking encoder, and decoding by an offset table.

encode_bpe: every whole text becomes token ids, exactly those of merging by rank.
A piece's candidate tokens come from one Aho-Corasick pass. The encoder takes the
longest token at each place as long as it may follow the one before: two tokens
may stand side by side if merging their joined bytes by rank gives those two
again, which a table of splits and pair merges answers without merging. A dead
end steps back once and marks the place, so the work is linear in the piece.

Contracts: a null text is empty; an empty text has no tokens; special tokens'
strings in a text become their ids, as the library does by default; no row is
dropped, repeated rows give repeated rows; other columns are ignored.
"""

from __future__ import annotations

import functools
import hashlib
import json
import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import DataFrame, SparkSession

from pathload.llm.common import table

#: Pieces kept with their ids by a worker; the table is emptied when it is full, which never changes results.
PIECES_KEPT = 300_000
#: Only texts of these letters take the built-in regex engine; in them both engines split alike.
_LETTER = "A-Za-zÀ-ÖØ-öø-ɏ"
_UNUSUAL = re.compile(rf"[^\t-\r\x20-\x7e{_LETTER}]")
_PLAIN = re.compile(rf"'s|'t|'re|'ve|'m|'ll|'d| ?[{_LETTER}]+| ?[0-9]+| ?[^\s{_LETTER}0-9]+|\s+(?!\S)|\s+")
_SPACES = r"\t-\r\x20\x85\xa0  -     　"
_ANY = regex.compile(rf"'s|'t|'re|'ve|'m|'ll|'d| ?\p{{L}}+| ?\p{{N}}+| ?[^{_SPACES}\p{{L}}\p{{N}}]+|[{_SPACES}]+(?![^{_SPACES}])|[{_SPACES}]+")


def byte_alphabet() -> dict[str, int]:
    """Printable stand-ins of byte-level vocabularies: visible Latin-1 bytes stand for themselves, others follow from U+0100."""
    plain = [*range(0x21, 0x7F), *range(0xA1, 0xAD), *range(0xAE, 0x100)]
    rest = [b for b in range(256) if b not in set(plain)]
    return {chr(b): b for b in plain} | {chr(256 + i): b for i, b in enumerate(rest)}


class BacktrackingBpe:
    """Tables of one vocabulary: automaton, splits, pair merges, ids and the decoder's offsets."""

    def __init__(self, path: str):
        import ahocorasick

        with open(path, encoding="utf-8") as f:
            spec = json.load(f)
        vocab = spec["model"]["vocab"]
        merges = [tuple(m.split(" ")) if isinstance(m, str) else tuple(m) for m in spec["model"]["merges"]]
        alphabet = byte_alphabet()
        raw = lambda s: bytes(alphabet[c] for c in s)
        names = sorted(alphabet, key=alphabet.get) + [a + b for a, b in merges]
        place = {s: i for i, s in enumerate(names)}
        self.token = [raw(s) for s in names]
        self.size = [len(t) for t in self.token]
        self.id_bytes = [int(vocab[s]).to_bytes(4, "little") if s in vocab else b"" for s in names]
        self.left, self.right = list(range(len(names))), list(range(len(names)))
        self.merged: dict[int, int] = {}
        for i, (a, b) in enumerate(merges):
            k = 256 + i
            self.left[k], self.right[k] = place[a], place[b]
            self.merged[place[a] << 20 | place[b]] = k
        self.automaton = ahocorasick.Automaton()
        for i, t in enumerate(self.token):
            if i >= 256:
                self.automaton.add_word(t.decode("latin-1"), (self.size[i] - 1, i))
        self.automaton.make_automaton()
        self.special = {a["content"]: int(a["id"]).to_bytes(4, "little") for a in spec.get("added_tokens", [])}
        self.at_special = re.compile("(" + "|".join(re.escape(s) for s in sorted(self.special, key=len, reverse=True)) + ")") if self.special else None
        by_id: dict[int, bytes] = {vocab[s]: t for s, t in zip(names, self.token, strict=True) if s in vocab}
        by_id |= {a["id"]: a["content"].encode() for a in spec.get("added_tokens", [])}
        parts = [by_id.get(i, b"") for i in range(max(by_id) + 1)]
        self.spelled = np.frombuffer(b"".join(parts), np.uint8)
        self.spelled_at = np.concatenate([[0], np.cumsum([len(p) for p in parts])]).astype(np.int64)
        self.pieces: dict[str, bytes] = {}
        self.fits: dict[int, bool] = {}

    def _compatible(self, a: int, b: int) -> bool:
        """Whether merging the joined bytes of a and b by rank leaves exactly a and b.

        It undoes the later of the two tokens step by step: if a pair that meets
        at the border merges before the token that would have to exist first,
        the border doesn't hold.
        """
        key = a << 20 | b
        known = self.fits.get(key)
        if known is not None:
            return known
        bound, x, y, good = len(self.token), a, b, None
        while good is None:
            if self.merged.get(x << 20 | y, bound) < bound:
                good = False
            elif x > y:  # x was made later: before that its right part stood at the border
                bound, x = x, self.right[x]
                if x == bound:
                    bound, y = y + 1, self.left[y]
                    good = True if y + 1 == bound else None
            else:
                bound, y = y + 1, self.left[y]
                if y + 1 == bound:
                    bound, x = x, self.right[x]
                    good = True if x == bound else None
        if len(self.fits) > 250_000:
            self.fits.clear()
        self.fits[key] = good
        return good

    def _piece(self, piece: str) -> bytes:
        text = piece.encode("utf-8", "surrogatepass")
        n = len(text)
        if n == 1:
            return self.id_bytes[text[0]]
        found: list[list[int]] = [[b] for b in text]  # single bytes are tokens 0 to 255
        for end, (before, token) in self.automaton.iter(text.decode("latin-1")):
            found[end - before].append(token)  # ends rise, so each list goes from short to long
        dead = bytearray(n + 1)
        chosen: list[tuple[int, int]] = []  # token, its index among its start's candidates
        at, pick = 0, len(found[0]) - 1
        while at < n:
            token = found[at][pick] if pick >= 0 else None
            if token is None:
                dead[at] = 1
                back, pick = chosen.pop()
                at -= self.size[back]
                pick -= 1
            elif not dead[at + self.size[token]] and (not chosen or self._compatible(chosen[-1][0], token)):
                chosen.append((token, pick))
                at += self.size[token]
                pick = len(found[at]) - 1 if at < n else 0
            else:
                pick -= 1
        return b"".join([self.id_bytes[t] for t, _ in chosen])

    def _plain(self, text: str) -> list[bytes]:
        kept, out = self.pieces, []
        for p in (_ANY if _UNUSUAL.search(text) else _PLAIN).findall(text):
            ids = kept.get(p)
            if ids is None:
                ids = self._piece(p)
                if len(p) < 64:
                    if len(kept) >= PIECES_KEPT:
                        kept.clear()
                    kept[p] = ids
            out.append(ids)
        return out

    def encode(self, text: str) -> bytes:
        """Ids as little-endian unsigned 32-bit integers."""
        if self.at_special is None or not any(s in text for s in self.special):
            return b"".join(self._plain(text))
        out: list[bytes] = []
        for part in self.at_special.split(text):
            if part in self.special:
                out.append(self.special[part])
            elif part:
                out += self._plain(part)
        return b"".join(out)

    def decode(self, ids: bytes) -> bytes:
        """Bytes of the ids: slices of one table, gathered by offsets, about a million bytes at a time."""
        out = []
        every = np.frombuffer(ids, np.uint32)
        for a in range(0, len(every), 1 << 17):
            part = every[a : a + (1 << 17)]
            start, size = self.spelled_at[part], self.spelled_at[part + 1] - self.spelled_at[part]
            before = np.cumsum(size) - size
            where = np.arange(int(size.sum())) + np.repeat(start - before, size)
            out.append(self.spelled[where].tobytes())
        return b"".join(out)


@functools.lru_cache(maxsize=4)
def vocabulary(path: str) -> BacktrackingBpe:
    return BacktrackingBpe(path)


def default_path(name: str = "byte_bpe_50k.json") -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


def encode_bpe(docs: DataFrame, path: str | None = None, key: str = "doc_id", text: str = "text") -> DataFrame:
    """(key, ids binary): the ids of each whole text, little-endian unsigned 32-bit."""
    path = path or default_path()

    def encode(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        bpe = vocabulary(path)
        for b in batches:
            for a in range(0, b.num_rows, 1024):
                part = b.slice(a, 1024)
                ids = [bpe.encode(t.as_py() or "") for t in part.column(1)]
                yield pa.RecordBatch.from_arrays([part.column(0), pa.array(ids, pa.binary())], [key, "ids"])

    kept = docs.select(key, text)
    return kept.mapInArrow(encode, f"`{key}` {kept.schema[key].dataType.simpleString()}, ids binary")


def decode_bpe(encoded: DataFrame, path: str | None = None, key: str = "doc_id") -> DataFrame:
    """(key, ids, text) from (key, ids); bytes that are no UTF-8 become replacement characters."""
    path = path or default_path()

    def decode(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        bpe = vocabulary(path)
        for b in batches:
            texts = [bpe.decode(i.as_py() or b"").decode("utf-8", "replace") for i in b.column(1)]
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), pa.array(texts, pa.string())], [key, "ids", "text"])

    kept = encoded.select(key, "ids")
    return kept.mapInArrow(decode, f"`{key}` {kept.schema[key].dataType.simpleString()}, ids binary, text string")


def op7_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    from pyspark.sql import functions as F

    done = decode_bpe(encode_bpe(table(spark, sf_dir, "documents")))
    return done.select(
        "doc_id",
        (F.length("ids") / 4).cast("long").alias("n_tokens"),
        F.sha2("ids", 256).alias("ids_sha256"),
        F.sha2(F.encode("text", "UTF-8"), 256).alias("decoded_sha256"),
    )


def digest(ids: bytes) -> str:
    return hashlib.sha256(ids).hexdigest()
