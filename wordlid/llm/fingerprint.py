"""Document fingerprints from prefix polynomial hashes.

The prefix hashes of a text, under two primes, answer whether any two spans are equal without looking at them
again, and the longest common extension of two places by binary search. A fingerprint keeps the length, the hash of the whole,
and the hashes of content-defined spans that cover the whole text, all from the prefix arrays. A span ends where a hash of the last few
characters ends in so many zero bits that there are 32 to 64 spans, so the same passage has the same spans wherever it stands;
the spans of a longer text are those of a shorter one put together, as the hash of two spans in a row follows from theirs.
Two fingerprints' likeness is the share of the longer text that lies in spans which both have. For texts that are too short or too even to have
spans, hashes of a ladder of prefixes are kept as well, and texts are at least as alike as their common beginning is long, to within a rung.

The next document in ascending doc_id is found without a global sort in one task: documents are dealt by explicit
cut points, each part is read in order, and the first document of each part is also sent to the part before.

Nulls: a null text is empty; empty texts have equal fingerprints, alike by 1. Rows with a null doc_id come first; rows
with the same doc_id follow each other by the 64-bit hash of the text, so many rows under one doc_id are dealt like others. A single row is its own next document. An empty table gives an empty
result; extra columns are ignored, whatever their names.
"""

from __future__ import annotations

import base64
import functools
import hashlib
import math
from collections import Counter
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from wordlid.io import bound_batches, small_table
from wordlid.llm.arrowtext import ODD, mapped, mixed

PRIMES = (2147483647, 2147483629)
BASES = (1000003, 69069)
#: Characters that decide whether a span ends behind them; a text is cut into SPANS spans or up to twice as many.
WINDOW, SPANS = 6, 32
#: Texts with fewer code points keep the hashes of all their prefixes; others, from this length on, of RUNGS for each doubling.
SHORT, RUNGS = 64, 8
#: Bytes of a part; a table of 512 MB is dealt into PARTS parts, and their number and size grow with larger ones.
PARTS = 128


@functools.cache
def _powers(which: int, bits: int) -> np.ndarray:
    p, out = PRIMES[which], np.ones(1, np.uint64)
    step = np.uint64(BASES[which])
    for _ in range(bits):
        out = np.concatenate([out, out * step % np.uint64(p)])
        step = step * step % np.uint64(p)
    return out


class PrefixHashes:
    """H[i] = sum of code[j] * base**j, j < i, modulo each prime."""

    def __init__(self, text: str):
        self.codes = np.frombuffer(text.encode("utf-32-le", "surrogatepass"), np.uint32).astype(np.uint64) + np.uint64(1)
        codes = self.codes
        self.n, self.bits = len(codes), max(1, int(len(codes)).bit_length())
        self.prefix = []
        for k, p in enumerate(PRIMES):
            terms = codes * _powers(k, self.bits)[: self.n] % np.uint64(p)
            # a sum of 2**32 terms below 2**31 fits into 64 bits
            self.prefix.append(np.concatenate([[np.uint64(0)], np.cumsum(terms, dtype=np.uint64) % np.uint64(p)]))

    def span(self, start, end, at: int) -> tuple[np.ndarray, ...]:
        """Hash of [start, end) as if it began at place `at`, which is not before start."""
        out = []
        for k, p in enumerate(PRIMES):
            h = self.prefix[k]
            part = (h[end] + np.uint64(p) - h[start]) % np.uint64(p)
            out.append(part * _powers(k, max(1, int(at).bit_length()))[at - np.asarray(start)] % np.uint64(p))
        return tuple(out)

    def equal(self, start: int, other: PrefixHashes, begin: int, size: int) -> bool:
        """Whether [start, start + size) here and [begin, begin + size) there are the same."""
        for k, p in enumerate(PRIMES):
            mine = int(self.prefix[k][start + size]) - int(self.prefix[k][start])
            theirs = int(other.prefix[k][begin + size]) - int(other.prefix[k][begin])
            # both brought to the later place
            shift = int(_powers(k, max(1, abs(begin - start).bit_length()))[abs(begin - start)])
            if (mine * (shift if start < begin else 1) - theirs * (shift if begin < start else 1)) % p:
                return False
        return True

    def extension(self, start: int, other: PrefixHashes, begin: int) -> int:
        """Length of the longest common run from start here and begin there."""
        low, high = 0, min(self.n - start, other.n - begin)
        while low < high:
            middle = (low + high + 1) // 2
            if self.equal(start, other, begin, middle):
                low = middle
            else:
                high = middle - 1
        return low


SPAN = np.dtype([("size", ">u4"), ("level", "u1"), ("a", ">u4"), ("b", ">u4")])


def level(n: int) -> int:
    """Zero bits at which a text of n code points is cut."""
    return max(2, (n // SPANS).bit_length() - 1)


def spans(h: PrefixHashes) -> np.ndarray:
    """Size, level of the end (zero bits of the window's hash) and both hashes of each span of a text."""
    bits = level(h.n)
    roll = np.zeros(max(0, h.n - WINDOW), np.uint64)  # of the windows that end before the last character
    for k in range(WINDOW):
        roll = roll * ODD + h.codes[k : k + len(roll)]
    roll = mixed(roll)
    at = np.flatnonzero((roll & np.uint64((1 << bits) - 1)) == 0)
    zeros = roll[at]
    ends = np.append(at + WINDOW, h.n)
    starts = np.append(0, ends[:-1])
    out = np.zeros(len(ends), SPAN)
    out["size"] = ends - starts
    low = zeros & (~zeros + np.uint64(1))
    out["level"] = np.append(np.where(low > 0, np.log2(np.maximum(low, 1).astype(float)), 63).astype(np.uint8), 63)
    for k, (name, values) in enumerate(zip("ab", h.span(starts, ends, h.n), strict=True)):
        # hashed as if they began at n, and brought back to one place for all texts
        out[name] = values * _inverse(k, h.n) % np.uint64(PRIMES[k])
    return out


def _inverse(which: int, n: int) -> np.uint64:
    """base ** -n: moves a hash that begins at n to place 0."""
    return np.uint64(pow(BASES[which], -n, PRIMES[which]))


def coarser(parts: np.ndarray, bits: int) -> np.ndarray:
    """The spans of the same text cut at a higher level: neighbours are joined over the ends that fall short of it."""
    last = np.flatnonzero(parts["level"] >= bits)
    first = np.append(0, last[:-1] + 1)
    if len(last) == len(parts):
        return parts
    out = parts[last]
    sizes = parts["size"].astype(np.int64)
    before = np.cumsum(sizes) - sizes
    place = before - np.repeat(before[first], last - first + 1)  # of each span in its new one
    for k, name in enumerate("ab"):
        shift = np.array([pow(BASES[k], int(x), PRIMES[k]) for x in place], np.uint64)
        out[name] = np.add.reduceat(parts[name].astype(np.uint64) * shift % np.uint64(PRIMES[k]), first) % np.uint64(PRIMES[k])
    out["size"] = np.add.reduceat(sizes, first)
    return out


@functools.lru_cache(1024)
def ladder(bits: int) -> np.ndarray:
    """Lengths of the prefixes of texts of fewer than 2 ** bits code points that are hashed."""
    if 1 << bits <= SHORT:
        return np.arange(1, 1 << bits)
    return np.unique((SHORT * 2.0 ** (np.arange((bits - SHORT.bit_length() + 1) * RUNGS) / RUNGS)).astype(np.int64))


def rungs(n: int) -> np.ndarray:
    out = ladder(n.bit_length())
    return out[out <= n]


def fingerprint(text: str) -> str:
    """length:whole:spans:prefixes, the first two in hexadecimal, the others in base 64."""
    return _printed(PrefixHashes(text))


def _printed(h: PrefixHashes) -> str:
    whole = [int(p[h.n]) for p in h.prefix]
    at = rungs(h.n)
    front = (h.prefix[0][at] ^ (h.prefix[1][at] * ODD >> np.uint64(32))).astype(">u4")
    return f"{h.n:x}:{whole[0]:08x}{whole[1]:08x}:{base64.b64encode(spans(h).tobytes()).decode() if h.n else ''}:{base64.b64encode(front.tobytes()).decode()}"


@functools.lru_cache(8)
def _read(printed: str) -> tuple[int, np.ndarray, np.ndarray]:
    n, _, parts, front = printed.split(":")
    return int(n, 16), np.frombuffer(base64.b64decode(parts), SPAN), np.frombuffer(base64.b64decode(front), ">u4")


def likeness(a: str, b: str) -> float:
    """Share of the longer text that lies in spans which both texts have, each as often as both have it, or in their common beginning."""
    if a == b:
        return 1.0
    (n, x, front), (m, y, front2) = _read(a), _read(b)
    if not n or not m:
        return 0.0
    bits = max(level(n), level(m))
    x, y = Counter(coarser(x, bits)[["size", "a", "b"]].tolist()), Counter(coarser(y, bits)[["size", "a", "b"]].tolist())
    common = sum(min(k, y[s]) * s[0] for s, k in x.items() if s in y)
    if (n < SHORT) == (m < SHORT):  # hashes of prefixes of the same lengths
        least = min(len(front), len(front2))
        same = np.append(front[:least] == front2[:least], False)
        if same[0]:
            common = max(common, int(rungs(max(n, m))[int(same.argmin()) - 1]))
    return common / max(n, m)


def edited(text: str, following: str) -> str:
    """text with its last quarter replaced by as many of the first code points of what follows."""
    k = len(text) // 4
    return text[: len(text) - k] + following[:k]


def _paired(batches: Iterator[pa.RecordBatch]) -> Iterator[tuple[int, str, str]]:
    """Each row with its next one's text; rows that only look ahead come last in their part."""
    held, part = None, None
    for batch in batches:
        ids, texts = batch.column("doc_id").to_pylist(), batch.column("text")
        parts, ahead = batch.column("part").to_pylist(), batch.column("ahead").to_pylist()
        for i in range(batch.num_rows):
            text = texts[i].as_py() or ""
            if held is not None and parts[i] == part:
                yield (*held, text)
            held, part = (None if ahead[i] else (ids[i], text)), parts[i]


SCHEMA = "doc_id long, n_chars long, edited_sha256 string, fingerprint string, edited_fingerprint string, near_edited double, near_next double, front_edited long, front_next long"
NAMES = [x.split(" ")[0] for x in SCHEMA.split(", ")]


def _fingerprints(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    rows, kept = [], ("", None, "")
    for doc_id, text, following in _paired(batches):
        new = edited(text, following)
        if kept[1] is None or text != kept[0]:
            h = PrefixHashes(text)
            kept = (text, h, _printed(h))
        _, h, own = kept
        g = h if new == text else PrefixHashes(new)
        changed = own if new == text else _printed(g)
        if following != text:
            after = PrefixHashes(following)
            kept = (following, after, _printed(after))
        digest = hashlib.sha256(new.encode("utf-8", "replace")).hexdigest()
        rows.append((doc_id, len(text), digest, own, changed, likeness(own, changed), likeness(own, kept[2]), h.extension(0, g, 0), h.extension(0, kept[1], 0)))
        if len(rows) == 1000:
            yield _batch(rows)
            rows = []
    if rows:
        yield _batch(rows)


def _batch(rows: list[tuple]) -> pa.RecordBatch:
    kinds = {"long": pa.int64(), "string": pa.string(), "double": pa.float64()}
    return pa.RecordBatch.from_arrays([pa.array(c, kinds[x.split(" ")[1]]) for c, x in zip(zip(*rows, strict=True), SCHEMA.split(", "), strict=True)], names=NAMES)


LEAST = -(1 << 63)


def _part_of(bounds):
    """The number of cut points (doc_id, hash) that a row does not come before; a null doc_id comes before all others."""

    def part(doc_id: pa.Array, h: pa.Array) -> pa.Array:
        cut_id, cut_hash = bounds.value
        ids, hashes = pc.fill_null(doc_id, LEAST).to_numpy(zero_copy_only=False), h.to_numpy(zero_copy_only=False)
        low, high = np.searchsorted(cut_id, ids, side="left"), np.searchsorted(cut_id, ids, side="right")
        out = low.astype(np.int64)
        for i in np.unique(low[low < high]):  # rows under a doc_id that is a cut point's
            mine = (low == i) & (low < high)
            out[mine] = i + np.searchsorted(cut_hash[i : high[mine][0]], hashes[mine], side="right")
        return pa.array(out)

    return F.arrow_udf(part, "long")


def with_next(docs: DataFrame, parts: int | None = None) -> DataFrame:
    """doc_id, text, part, ahead, dealt so that each part is in ascending order and ends with the first row of the next."""
    spark = docs.sparkSession
    bound_batches(spark)
    docs = docs.select("doc_id", "text", F.xxhash64(F.coalesce("text", F.lit(""))).alias("h"))
    rows, size = docs.agg(F.count("*"), F.sum(F.octet_length("text"))).first()
    if parts is None:
        parts = max(1, math.ceil(PARTS * ((size or 0) / 2**29) ** (2 / 3)))
    # the driver holds some forty rows of a few bytes for each part
    limit = int(min(1.0, 40 * parts / max(rows, 1)) * (1 << 30))
    some = docs.filter(F.pmod(F.xxhash64(F.lit(6), "doc_id", "h"), F.lit(1 << 30)) < limit).select(F.coalesce("doc_id", F.lit(LEAST)).alias("i"), "h").toArrow()
    ids, hashes = some["i"].to_numpy(), some["h"].to_numpy()
    order = np.lexsort((hashes, ids))[np.arange(1, parts) * len(ids) // parts] if len(ids) else np.zeros(0, np.int64)
    cuts = np.unique(np.stack([ids[order], hashes[order]], 1), axis=0)
    part_of = _part_of(spark.sparkContext.broadcast((cuts[:, 0].copy(), cuts[:, 1].copy())))
    dealt = docs.withColumn("part", part_of("doc_id", "h"))
    first = F.min(F.struct(F.col("doc_id").isNotNull().alias("known"), "doc_id", "h")).alias("head")
    heads = dealt.drop("text").groupBy("part").agg(first).select("part", "head.*").orderBy("part").toArrow()
    if not heads.num_rows:
        return docs.select("doc_id", "text", F.lit(0).cast("long").alias("part"), F.lit(False).alias("ahead"))
    # the part before looks ahead at the first row of a part; the last one, at the first of all
    before = np.roll(heads["part"].to_numpy(), 1)
    small = small_table(spark, _head=heads["doc_id"].combine_chunks(), _h=heads["h"].combine_chunks(), _before=pa.array(before))
    found = docs.join(F.broadcast(small), F.col("doc_id").eqNullSafe(F.col("_head")) & (F.col("h") == F.col("_h")))
    texts = found.groupBy("_before").agg(F.min("text").alias("text"))
    ahead = texts.select(F.lit(None).cast("long").alias("doc_id"), "text", F.lit(0).cast("long").alias("h"), F.col("_before").alias("part"), F.lit(True).alias("ahead"))
    every = dealt.withColumn("ahead", F.lit(False)).select("doc_id", "text", "h", "part", "ahead").unionByName(ahead)
    return every.repartition(heads.num_rows, "part").sortWithinPartitions("part", "ahead", F.asc_nulls_first("doc_id"), "h", "text").drop("h")


def fingerprints(docs: DataFrame, parts: int | None = None) -> DataFrame:
    """For each document its fingerprint, its edited text's, how near they and the next one's are, and how far the texts themselves
    agree from their beginning (front_*, by binary search on the prefix hashes)."""
    return mapped(with_next(docs, parts), _fingerprints, SCHEMA)
