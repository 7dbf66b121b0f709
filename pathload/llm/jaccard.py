"""N-gram Jaccard join by rare-first prefix filtering.

A text's set is its distinct word shingles. All sets share one order of shingles,
rarest first, from a frequency table of fixed size that counts every document. Two
sets of at least the threshold share a shingle among the first n - ceil(t n) + 1 of
each, so only those are posted. Postings of shingles that one set alone has are
dropped where they meet. What is left gives candidates through length, positional
and suffix filters, and each candidate pair is verified once against the texts, by
comparing the bytes of words.

Texts with equal sets are one class, named by two fingerprints and the size and
stood for by its smallest id; only that text has postings. To link classes without
emitting all pairs of a large group, each shingle's postings are first compared with
one set of that shingle only, then with one of those that agree with it in some
parity bits; the remaining pairs that lie in different components, and only those,
are verified then. No link between components can be missed, as every pair that
passes the filters is verified or already connected.

Contracts: ids are whole numbers; null and empty texts, and texts without words,
have empty sets and are linked with nothing; rows of equal text are one class; rows
of equal id are one document for links, whatever their texts; a row with a null id
is its own, with a null component; an empty table gives an empty result.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, functions as F

from pathload.llm.common import U64, bucket_of, doc_slices, group_count, mix64, packed, run_hashes, run_numbers, staged, table, text_buffer, unpacked, word_hashes, word_numbers, word_spans
from pathload.operators.components import component_roots

#: Cells of the frequency table; it has this size for any input.
CELLS = 1 << 18
POSTING = np.dtype([("token", "<u8"), ("set", "<i8"), ("parts", "<i8"), ("n", "<u4"), ("at", "<u4")])
BITS = ("b0", "b1", "b2", "b3")
_UPPER = np.zeros(256, np.uint8)
_UPPER[65:91] = 32


def shingles(data: np.ndarray, off: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray]:
    """(hash, document) of every shingle of some texts, repeats included."""
    low = data + _UPPER[data]
    start, end, words = word_spans(low, off)
    h = word_hashes(low, start, end)
    runs = run_hashes(h, k)
    doc = np.repeat(np.arange(len(off) - 1), np.diff(words))
    inside = np.arange(len(runs)) + k <= words[1:][doc[: len(runs)]]
    runs, own = runs[inside], doc[: len(inside)][inside]
    count = np.diff(words)
    short = np.flatnonzero((count > 0) & (count < k))
    if len(short):
        extra = np.array([run_hashes(h[words[d] : words[d + 1]], int(count[d]), 1)[0] + U64(count[d]) for d in short.tolist()], U64)
        runs, own = np.concatenate([runs, extra]), np.concatenate([own, short])
    return runs, own


def distinct_sets(data: np.ndarray, off: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray]:
    """Sorted distinct shingles of each text, and the texts' offsets into them."""
    h, doc = shingles(data, off, k)
    order = np.lexsort((h, doc))
    h, doc = h[order], doc[order]
    new = np.append(True, (h[1:] != h[:-1]) | (doc[1:] != doc[:-1])) if len(h) else np.zeros(0, bool)
    h, doc = h[new], doc[new]
    return h, np.searchsorted(doc, np.arange(len(off)))


def _sums(x: np.ndarray, at: np.ndarray) -> np.ndarray:
    total = np.concatenate([np.zeros(1, x.dtype), np.cumsum(x)])
    return total[at[1:]] - total[at[:-1]]


def set_names(h: np.ndarray, at: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Two independent 64-bit fingerprints of each set."""
    return mix64(_sums(mix64(h), at)).view(np.int64), mix64(_sums(mix64(h ^ U64(0xA5A5A5A5A5A5A5A5)), at)).view(np.int64)


def parities(h: np.ndarray, at: np.ndarray) -> list[np.ndarray]:
    """Four words of 64 bits a set: whether each of 256 hash parts holds an odd number of shingles.

    Bits in which two sets differ are at most the shingles in which they differ.
    """
    part = ((h >> U64(20)) & U64(255)).astype(np.int64)
    out = []
    for w in range(4):
        bits = np.where(part >> 6 == w, U64(1) << (part & 63).astype(U64), U64(0))
        total = np.concatenate([np.zeros(1, U64), np.bitwise_xor.accumulate(bits)]) if len(bits) else np.zeros(1, U64)
        out.append((total[at[1:]] ^ total[at[:-1]]).view(np.int64))
    return out


def frequencies(docs: DataFrame, k: int, text: str = "text") -> np.ndarray:
    """How often shingles of each cell occur in all documents; a table of CELLS numbers."""

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = np.zeros(CELLS, np.int64)
        for b in batches:
            data, off = text_buffer(b.column(0))
            for x, y in doc_slices(off):
                h, _ = shingles(data[off[x] : off[y]], off[x : y + 1] - off[x], k)
                total += np.bincount((h & U64(CELLS - 1)).astype(np.int64), minlength=CELLS)
        cell = np.flatnonzero(total)
        records = np.empty(len(cell), np.dtype([("cell", "<u4"), ("n", "<u4")]))
        records["cell"], records["n"] = cell, np.minimum(total[cell], 2**32 - 1)
        made = packed(cell // (CELLS // 64), records)
        yield pa.RecordBatch.from_arrays(made.columns, ["bucket", "block"])

    def add(rows: pa.Table) -> pa.Table:
        r = unpacked(rows.column("block"), np.dtype([("cell", "<u4"), ("n", "<u4")]))
        first = int(r["cell"][0]) // (CELLS // 64) * (CELLS // 64) if len(r) else 0
        total = np.bincount(r["cell"].astype(np.int64) - first, r["n"].astype(float), CELLS // 64).astype(np.int64)
        return pa.table({"bucket": pa.array([first], pa.int32()), "block": pa.array([total.tobytes()], pa.binary())})

    merged = docs.select(text).mapInArrow(count, "bucket int, block binary").groupBy("bucket").applyInArrow(add, "bucket int, block binary")
    out = np.zeros(CELLS, np.int64)
    for row in merged.collect():  # CELLS numbers in all
        out[row["bucket"] : row["bucket"] + CELLS // 64] = np.frombuffer(row["block"], np.int64)
    return out


def _ceil_share(n, t: int):
    return (t * n + 99) // 100


def describe_sets(docs: DataFrame, k: int, key: str = "doc_id", text: str = "text") -> DataFrame:
    """(key, digest, n_shingles, set, set2, b0 to b3): a hash of each text; its set's size, fingerprints and parities."""

    def describe(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            data, off = text_buffer(b.column(2))
            for x, y in doc_slices(off):
                h, at = distinct_sets(data[off[x] : off[y]], off[x : y + 1] - off[x], k)
                s, s2 = set_names(h, at)
                part = b.slice(x, y - x)
                yield pa.RecordBatch.from_arrays([part.column(0), part.column(1), pa.array(np.diff(at)), pa.array(s), pa.array(s2), *map(pa.array, parities(h, at))], [key, "digest", "n_shingles", "set", "set2", *BITS])

    kept = docs.select(key, F.xxhash64(text).alias("digest"), text)
    return kept.mapInArrow(describe, f"`{key}` {kept.schema[key].dataType.simpleString()}, digest bigint, n_shingles bigint, set bigint, set2 bigint, b0 bigint, b1 bigint, b2 bigint, b3 bigint")


def prefix_postings(texts: DataFrame, often: np.ndarray, k: int, t: int) -> DataFrame:
    """(token, set, parts, n, at): postings of prefix shingles that at least two sets have. texts: (set, text), one for each class.

    parts: how many shingles behind this one lie in each of four hash quarters, sixteen bits each, for the suffix filter.
    """
    rank = np.minimum(np.log2(often + 1) * 8, 255).astype(np.uint8)
    owners = group_count(texts, 4 << 20, 2)

    def post(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            names = b.column(0).to_numpy()
            data, off = text_buffer(b.column(1))
            out = [np.zeros(0, POSTING)]
            for x, y in doc_slices(off):
                h, at = distinct_sets(data[off[x] : off[y]], off[x : y + 1] - off[x], k)
                if not len(h):
                    continue
                n = np.diff(at)
                doc = np.repeat(np.arange(len(n)), n)
                h = h[np.lexsort((h, rank[(h & U64(CELLS - 1)).astype(np.int64)], doc))]
                place = np.arange(len(h)) - at[:-1][doc]
                use = np.flatnonzero(place < (n - _ceil_share(n, t) + 1)[doc])
                d = doc[use]
                r = np.empty(len(use), POSTING)
                r["token"], r["set"], r["n"], r["at"] = h[use], names[x:y][d], n[d], place[use]
                parts = np.zeros(len(use), np.int64)
                for q in range(4):
                    total = np.concatenate([[0], np.cumsum((h >> U64(60)) & U64(3) == q)])
                    parts |= np.minimum(total[at[1:]][d] - total[use + 1], 0x7FFF) << (16 * q)
                r["parts"] = parts
                out.append(r)
            r = np.concatenate(out)
            yield packed(bucket_of(r["token"], owners), r)

    def meet(rows: pa.Table) -> pa.Table:
        r = unpacked(rows.column("block"), POSTING)
        r = r[np.lexsort((r["set"], r["token"]))]
        same = r[1:] == r[:-1]
        r = r[np.append(True, ~same)] if len(r) else r
        cut = np.append(True, r["token"][1:] != r["token"][:-1]) if len(r) else np.zeros(0, bool)
        size = np.diff(np.append(np.flatnonzero(cut), len(r)))
        r = r[np.repeat(size > 1, size)]
        return pa.table({"token": pa.array(r["token"].astype(U64).view(np.int64)), "set": pa.array(r["set"].copy()), "parts": pa.array(r["parts"].copy()), "n": pa.array(r["n"].astype(np.int64)), "at": pa.array(r["at"].astype(np.int64))})

    blocks = texts.select("set", "text").mapInArrow(post, "bucket int, block binary")
    return blocks.groupBy("bucket").applyInArrow(meet, "token bigint, set bigint, parts bigint, n bigint, at bigint")


def _filters(t: int):
    """Length, positional and suffix filters over postings x and y of one shingle, right where it is the first that both have.

    Behind it the sets differ in at least what the sizes of their suffixes' hash quarters differ, which bounds what they have in common.
    """
    nx, ny, ax, ay = F.col("x.n"), F.col("y.n"), F.col("x.at"), F.col("y.at")
    length = 100 * F.least(nx, ny) >= t * F.greatest(nx, ny)
    need = F.floor((t * (nx + ny) + (99 + t)) / (100 + t))  # least intersection
    positional = F.least(nx - ax, ny - ay) >= need
    part = lambda side, q: F.shiftright(F.col(f"{side}.parts"), 16 * q).bitwiseAND(F.lit(0xFFFF))
    apart = sum((F.abs(part("x", q) - part("y", q)) for q in range(1, 4)), F.abs(part("x", 0) - part("y", 0)))
    return length & positional & (apart <= nx - ax + ny - ay - 2 * need)


def _pairs(joined: DataFrame) -> DataFrame:
    return joined.select(F.least("x.set", "y.set").alias("p"), F.greatest("x.set", "y.set").alias("q")).where("p <> q").distinct()


def _stars(x: DataFrame, by: list[str], t: int, seed: int, more: list[str]) -> DataFrame:
    """Postings x joined with one of their group: of those with the fewest rarer shingles, which are most like the others, a random one."""
    first = F.struct("at", F.xxhash64("set", F.lit(seed)).alias("o"), "set", "parts", "n", *more)
    y = x.groupBy(*by).agg(F.min(first).alias("f")).select(*by, "f.*").alias("y")
    same = [F.col(f"x.{c}") == F.col(f"y.{c}") for c in by]
    return x.alias("x").join(y, same).where(_filters(t))


def star_candidates(postings: DataFrame, t: int) -> DataFrame:
    """(p, q): each posting with one posting of its shingle."""
    return _pairs(_stars(postings, ["token"], t, 1, []))


def near_candidates(postings: DataFrame, t: int, roots: DataFrame, sketches: DataFrame) -> DataFrame:
    """(p, q) of different components: stars among the postings of a shingle that agree in six parity bits.

    Each shingle looks at bits of its own, so a set meets as many others as it has
    shingles, mostly such as differ from it little; there is one pair a posting at most.
    """
    word = F.element_at(F.array(*BITS), (F.pmod("token", F.lit(4)) + 1).cast("int"))
    bits = F.call_function("shiftright", word, F.pmod(F.shiftright("token", 2), F.lit(58)).cast("int")).bitwiseAND(F.lit(63))
    x = _across(postings, roots).join(sketches, "set").withColumn("bits", bits).drop(*BITS)
    return _pairs(_stars(x, ["token", "bits"], t, 2, ["root"]).where("x.root <> y.root"))


def _across(postings: DataFrame, roots: DataFrame) -> DataFrame:
    """Postings with their sets' roots, of shingles whose sets lie in several components."""
    own = postings.join(roots.select(F.col("id").alias("set"), "root"), "set", "left").withColumn("root", F.coalesce("root", "set"))
    mixed = own.groupBy("token").agg(F.min("root").alias("r1"), F.max("root").alias("r2")).where("r1 <> r2").select("token")
    return own.join(mixed, "token", "left_semi")


def all_candidates(postings: DataFrame, t: int, roots: DataFrame, sketches: DataFrame) -> DataFrame:
    """(p, q): all pairs of different components that share a shingle's postings and pass the filters.

    sketches: (set, b0 to b3). Differing parity bits bound the sets' difference from
    below, so the suffix filter is decided inside the join.
    """
    own = staged(_across(postings, roots).join(sketches, "set"))
    x, y = own.alias("x"), own.alias("y")
    nx, ny = F.col("x.n"), F.col("y.n")
    odd = sum((F.bit_count(F.col(f"x.{b}").bitwiseXOR(F.col(f"y.{b}"))) for b in BITS[1:]), F.bit_count(F.col("x.b0").bitwiseXOR(F.col("y.b0"))))
    near = odd <= nx + ny - 2 * F.floor((t * (nx + ny) + (99 + t)) / (100 + t))
    return _pairs(x.join(y, (F.col("x.token") == F.col("y.token")) & (F.col("x.root") < F.col("y.root")) & _filters(t) & near))


def exact_sets(data: np.ndarray, off: np.ndarray, k: int) -> list[np.ndarray]:
    """Each text's distinct shingles as sorted numbers, equal for equal words only; the numbers hold within one call."""
    low = data + _UPPER[data]
    start, end, words = word_spans(low, off)
    number, _ = word_numbers(low, start, end)
    runs = run_numbers(number, k)
    short: dict[bytes, int] = {}
    out = []
    for a, b in zip(words[:-1].tolist(), words[1:].tolist(), strict=True):
        if b - a >= k:
            out.append(np.unique(runs[a : b - k + 1]))
        else:  # the whole sequence is one shingle
            out.append(np.array([-1 - short.setdefault(number[a:b].tobytes(), len(short))] if b > a else [], np.int64))
    return out


def verified(pairs: DataFrame, texts: DataFrame, k: int, t: int) -> DataFrame:
    """(p, q) of the pairs whose texts' sets reach the threshold."""

    def verify(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            p, q = (text_buffer(b.column(i)) for i in (2, 3))
            names = b.column(0).to_numpy()
            good = np.zeros(b.num_rows, bool)
            for x, y in doc_slices(q[1]):
                # A left text stands once before its right texts.
                first = np.append(True, names[x + 1 : y] != names[x : y - 1])
                pieces, left, place = [], np.zeros(y - x, np.int64), np.zeros(y - x, np.int64)
                for i in range(x, y):
                    if not first[i - x] and not np.array_equal(p[0][p[1][i] : p[1][i + 1]], p[0][p[1][i - 1] : p[1][i]]):
                        first[i - x] = True  # an id with several texts
                    if first[i - x]:
                        pieces.append(p[0][p[1][i] : p[1][i + 1]])
                    left[i - x] = len(pieces) - 1 if first[i - x] else left[i - x - 1]
                    place[i - x] = len(pieces)
                    pieces.append(q[0][q[1][i] : q[1][i + 1]])
                off = np.concatenate([[0], np.cumsum([len(z) for z in pieces])]).astype(np.int64)
                sets = exact_sets(np.concatenate(pieces), off, k)
                for i, (u, v) in enumerate(zip(left.tolist(), place.tolist(), strict=True)):
                    a, c = sets[u], sets[v]
                    if len(a) and len(c):
                        at = np.minimum(np.searchsorted(a, c), len(a) - 1)
                        common = int((a[at] == c).sum())
                        good[x + i] = 100 * common >= t * (len(a) + len(c) - common)
            keep = pa.array(good)
            yield pa.RecordBatch.from_arrays([b.column(0).filter(keep), b.column(1).filter(keep)], ["p", "q"])

    right = pairs.join(texts.select(F.col("set").alias("q"), F.col("text").alias("tq")), "q")
    both = right.join(texts.select(F.col("set").alias("p"), F.col("text").alias("tp")), "p")
    return both.select("p", "q", "tp", "tq").mapInArrow(verify, "p bigint, q bigint")


def jaccard_components(docs: DataFrame, k: int = 5, t: int = 80, key: str = "doc_id", text: str = "text") -> DataFrame:
    """(key, n_shingles, component_id): components of the links of at least t hundredths."""
    docs = docs.select(F.col(key).cast("long").alias("id"), F.col(text).alias("text"))
    sets = staged(describe_sets(docs, k, "id"))
    name = ["set", "set2", "n_shingles"]
    top = F.min(F.struct("id", "digest")).alias("top")
    classes = staged(sets.where("n_shingles > 0 and id is not null").groupBy(*name).agg(top, *(F.min(b).alias(b) for b in BITS)))
    chosen = classes.select(F.col("top.id").alias("id"), F.col("top.digest").alias("digest"))
    texts = staged(docs.withColumn("digest", F.xxhash64("text")).join(chosen, ["id", "digest"]).select(F.col("id").alias("set"), "text"))
    postings = staged(prefix_postings(texts, frequencies(docs, k), k, t))
    sketches = classes.select(F.col("top.id").alias("set"), *BITS)
    links, tried, roots = None, None, None
    for step in ("first", "near", "all"):
        if step == "first":
            found = star_candidates(postings, t)
        else:
            found = (near_candidates if step == "near" else all_candidates)(postings, t, roots, sketches)
        if tried is not None:
            found = found.join(tried, ["p", "q"], "left_anti")
        found = staged(found)
        if found.isEmpty():
            if roots is None:  # every set is its own root
                roots = docs.sparkSession.createDataFrame([], "id bigint, root bigint")
            continue
        good = verified(found, texts, k, t)
        links = staged(good if links is None else links.unionByName(good))
        tried = found if tried is None else tried.unionByName(found)
        roots = staged(component_roots(links, "p", "q"))
    # A root is its component's smallest id.
    member = classes.select(*name, F.col("top.id").alias("first")).join(roots.select(F.col("id").alias("first"), "root"), "first", "left").select(*name, F.coalesce("root", "first").alias("component_id"))
    return sets.select("id", *name).join(member, name, "left").select(F.col("id").alias(key), "n_shingles", F.when(F.col("id").isNotNull(), F.coalesce("component_id", "id")).alias("component_id"))


def op4_jaccard(spark: SparkSession, sf_dir: str) -> DataFrame:
    return jaccard_components(table(spark, sf_dir, "documents"), 4, 85)


ORACLE = r"""
WITH RECURSIVE w AS (SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x20\x09-\x0D]+') AS words FROM documents),
s AS MATERIALIZED (SELECT DISTINCT doc_id, md5(g) AS g FROM (SELECT doc_id, CASE WHEN len(words) < 4 THEN array_to_string(words, ' ') ELSE array_to_string(list_slice(words, i, i + 3), ' ') END AS g
  FROM (SELECT doc_id, words, unnest(range(1, greatest(len(words) - 3, 1) + 1)) AS i FROM w WHERE len(words) > 0))),
n AS MATERIALIZED (SELECT doc_id, count(*) AS n FROM s GROUP BY 1),
links AS MATERIALIZED (SELECT a.doc_id AS x, b.doc_id AS y FROM s a JOIN s b ON a.g = b.g AND a.doc_id <> b.doc_id JOIN n na ON na.doc_id = a.doc_id JOIN n nb ON nb.doc_id = b.doc_id
  GROUP BY a.doc_id, b.doc_id, na.n, nb.n HAVING 100 * count(*) >= 85 * (na.n + nb.n - count(*))),
reach AS (SELECT x AS doc_id, x AS r FROM links UNION SELECT reach.doc_id, links.y FROM reach JOIN links ON links.x = reach.r),
least AS (SELECT doc_id, min(r) AS r FROM reach GROUP BY 1)
SELECT d.doc_id, coalesce(n.n, 0)::BIGINT AS n_shingles, least(d.doc_id, coalesce(l.r, d.doc_id)) AS component_id FROM documents d LEFT JOIN n USING (doc_id) LEFT JOIN least l USING (doc_id)
"""
