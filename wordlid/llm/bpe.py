"""BPE encoding and decoding with content-defined chunk reuse.

A rolling hash over the last bytes decides where a text is cut, always at the start of a word, so equal passages fall into
equal chunks whatever stands before them. Each distinct chunk, of some sixty words, is encoded once by a worker and serves all documents that
share it; documents are then put together from the chunks' token ids by array gathers. A new chunk is put together in the same way from
words that are known already and new ones, which the library encodes.

A cut is right only if nothing is merged across it. Between chunks, the last word before and the first word behind each join are
encoded together and apart: where the ids differ, the two words become one, the chunks on both sides become one and are encoded anew, and
their joins are tried again, until all that are left agree. Between words, each distinct neighbourhood of a cut (the character before the
white space, that space, and the character after it) is tried in that way, once, and cuts whose neighbourhood disagrees are no cuts.

Nulls: a null text is empty; an empty text has no ids and decodes to the empty text. Rows with a null
or repeated doc_id are encoded like others. An empty table gives an empty result; extra columns are ignored by counts and digests and kept by encode().
"""

from __future__ import annotations

import hashlib
import os
from collections.abc import Callable, Iterator
from itertools import chain

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from wordlid.llm.arrowtext import _space, mapped, mixed, pieces, utf8

#: Of 256 word starts, KEEP are cuts between words and CHUNKS are cuts between chunks; bytes that are worked on at once; words and chunks
#: that a worker remembers.
KEEP, CHUNKS, PIECE, MOST_KNOWN, MOST_CHUNKS = 256, 4, 1 << 20, 300_000, 20_000
ROLL = 6


def neighbours(part: np.ndarray, at: np.ndarray) -> np.ndarray:
    """For each place after a white-space byte: the code point before that byte, the byte, and the code point at the place, in one number."""
    byte = lambda i: part[np.clip(i, 0, len(part) - 1)].astype(np.uint64)

    def point(first: np.ndarray) -> np.ndarray:
        lead, out = byte(first), byte(first)
        more = (lead >= 0xC0).astype(int) + (lead >= 0xE0) + (lead >= 0xF0)
        out = np.where(more == 0, out, out & (np.uint64(0x3F) >> more.astype(np.uint64)))
        for k in range(1, 4):
            out = np.where(more >= k, out << np.uint64(6) | byte(first + k) & np.uint64(0x3F), out)
        return out

    start = at - 2
    for _ in range(3):
        start = start - ((byte(start) & np.uint64(0xC0)) == 0x80)
    return point(np.maximum(start, 0)) << np.uint64(29) | byte(at - 1) << np.uint64(21) | point(at)


class Memory:
    """Token ids by text, of a bounded number of texts."""

    def __init__(self, most: int):
        self.most, self.known = most, {}
        self.ids, self.ends, self.uses = np.zeros(0, np.int32), np.zeros(1, np.int64), np.zeros(0, np.int32)

    def forget(self) -> None:
        """Keep the texts that several pieces used, the most used ones up to half of what may be remembered; older uses count half."""
        kept = np.argsort(-self.uses, kind="stable")[: self.most // 2]
        kept = np.sort(kept[self.uses[kept] > 1])
        names = list(self.known)  # in the order of their places
        at, upto = spans(self.ends[kept], self.ends[kept + 1])
        self.ids = self.ids[at]
        self.known = {names[k]: i for i, k in enumerate(kept.tolist())}
        self.ends, self.uses = upto, self.uses[kept] // 2

    def new(self, texts: list[str]) -> list[int]:
        """Which of some distinct texts are not known; there is room for them then."""
        out = [i for i, t in enumerate(texts) if t not in self.known]
        if out and len(self.known) + len(out) > self.most:
            self.forget()
            out = [i for i, t in enumerate(texts) if t not in self.known]
        return out

    def add(self, texts: list[str], ids: np.ndarray, sizes) -> None:
        size = len(self.known)
        self.known.update(zip(texts, range(size, size + len(texts)), strict=True))
        self.ids = np.concatenate([self.ids, ids.astype(np.int32)])
        self.ends = np.concatenate([self.ends, self.ends[-1] + np.cumsum(sizes)])
        self.uses = np.concatenate([self.uses, np.zeros(len(texts), np.int32)])

    def gather(self, texts: list[str], which: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """The ids of texts[which], one after the other, and where those of each begin and the last ends."""
        place = np.array([self.known[t] for t in texts], np.int64)
        self.uses[place] += 1
        place = place[which]
        at, upto = spans(self.ends[place], self.ends[place + 1])
        return self.ids[at], upto


def spans(first: np.ndarray, end: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """All places of the spans [first, end), one after the other, and where each begins among them."""
    size = end - first
    upto = np.concatenate([[0], np.cumsum(size)])
    return np.repeat(first - upto[:-1], size) + np.arange(upto[-1]), upto


class ChunkEncoder:
    """Encodes batches of texts with one tokenizer file; lives in a Python worker."""

    _loaded: dict = {}

    @classmethod
    def of(cls, path: str, keep: int = KEEP) -> ChunkEncoder:
        """One encoder for each worker process, so that what it knows serves its later tasks."""
        if (path, keep) not in cls._loaded:
            cls._loaded[path, keep] = cls(path, keep)
        return cls._loaded[path, keep]

    def __init__(self, path: str, keep: int = KEEP, chunks: int = CHUNKS):
        os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")
        from tokenizers import Tokenizer

        self.tokenizer = Tokenizer.from_file(path)
        self.tokenizer.no_truncation()
        self.tokenizer.no_padding()
        self.keep, self.cut = keep, chunks
        self.joins: dict[int, bool] = {}
        self.seams: dict[tuple[str, str], bool] = {}
        self.words, self.chunks = Memory(MOST_KNOWN), Memory(MOST_CHUNKS)

    def encode(self, texts: list[str]) -> list[list[int]]:
        # a few thousand at a time: what the library returns for a text is a hundred times its ids
        return [e.ids for i in range(0, len(texts), 4096) for e in self.tokenizer.encode_batch_fast(texts[i : i + 4096], add_special_tokens=False)]

    def cuts(self, part: np.ndarray, heads: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Where words start in part, as far as the rolling hash picks them and their joins agree, and where chunks do; texts in heads start both."""
        black = ~_space[part]
        start = black.copy()
        start[1:] &= ~black[:-1]
        start[heads] = False
        at = np.flatnonzero(start)
        roll = np.zeros(len(at), np.uint64)
        for k in range(ROLL):
            roll = (roll << np.uint64(8)) | part[np.maximum(at - ROLL + k, 0)]
        roll = mixed(roll) % np.uint64(256)
        some = (roll < np.uint64(self.keep)) | (roll >= np.uint64(256 - self.cut))
        at, roll = at[some], roll[some]
        if len(at):
            coded = pa.array(neighbours(part, at)).dictionary_encode()
            joins = coded.dictionary.to_pylist()
            new = [j for j in joins if j not in self.joins]
            if len(self.joins) + len(new) > MOST_KNOWN:
                self.joins.clear()
                new = joins
            self._try_joins(new)
            right = np.array([self.joins[j] for j in joins])[coded.indices.to_numpy()]
            at, roll = at[right], roll[right]

        def with_heads(more: np.ndarray) -> np.ndarray:
            chosen = np.zeros(len(part), bool)
            chosen[heads] = chosen[more] = True
            return np.flatnonzero(chosen)

        return with_heads(at), with_heads(at[roll >= np.uint64(256 - self.cut)])

    def _try_joins(self, new: list[int]) -> None:
        """Whether both sides of a join, encoded together, give what they give apart."""
        left, right = [chr(j >> 29) + chr(j >> 21 & 255) for j in new], [chr(j & 0x1FFFFF) for j in new]
        whole = self.encode([a + b for a, b in zip(left, right, strict=True)])
        for j, w, a, b in zip(new, whole, self.encode(left), self.encode(right), strict=True):
            self.joins[j] = w == a + b

    def _ids(self, texts: list[str]) -> list[list[int]]:
        """Ids of words, which are remembered for the chunks that have them."""
        distinct = list(dict.fromkeys(texts))
        new = [distinct[i] for i in self.words.new(distinct)]
        if new:
            got = self.encode(new)
            self.words.add(new, np.fromiter(chain.from_iterable(got), np.int32), [len(x) for x in got])
        at = [self.words.known[t] for t in texts]
        return [self.words.ids[self.words.ends[k] : self.words.ends[k + 1]].tolist() for k in at]

    def repaired(self, part: np.ndarray, heads: np.ndarray, words: np.ndarray, chunks: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """words and chunks without the starts at which the words on both sides, encoded together, give other ids than apart."""
        while True:
            at = chunks[~np.isin(chunks, heads, assume_unique=True)]
            where = np.searchsorted(words, at)
            edge = np.append(words, len(part))
            text = lambda a, b: [part[x:y].tobytes().decode("utf-8", "replace") for x, y in zip(a.tolist(), b.tolist(), strict=True)]  # noqa: E731, B023
            pairs = list(zip(text(edge[where - 1], at), text(at, edge[where + 1]), strict=True))
            new = [p for p in dict.fromkeys(pairs) if p not in self.seams]
            if new:
                if len(self.seams) + len(new) > MOST_CHUNKS:
                    self.seams = {p: self.seams[p] for p in pairs if p in self.seams}
                apart = self._ids([x for p in new for x in p])
                for p, whole, a, b in zip(new, self.encode([a + b for a, b in new]), apart[::2], apart[1::2], strict=True):
                    self.seams[p] = whole == a + b
            wrong = at[~np.array([self.seams[p] for p in pairs], bool)]
            if not len(wrong):
                return words, chunks
            words, chunks = (x[~np.isin(x, wrong, assume_unique=True)] for x in (words, chunks))

    def run(self, data: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Token ids of the texts that offsets bound, one after the other, and each text's end."""
        n, low = len(offsets) - 1, int(offsets[0])
        part = np.ascontiguousarray(data[low : int(offsets[-1])])
        if not len(part):
            return np.zeros(0, np.int32), np.zeros(n + 1, np.int64)
        heads = np.unique(offsets[:-1][offsets[:-1] < offsets[1:]] - low)
        words, chunks = self.repaired(part, heads, *self.cuts(part, heads))
        column = lambda at: pa.LargeStringArray.from_buffers(len(at), pa.py_buffer(np.append(at, len(part)).astype(np.int64)), pa.py_buffer(part))
        coded = column(chunks).dictionary_encode()
        texts, kind = coded.dictionary.to_pylist(), coded.indices.to_numpy(zero_copy_only=False)
        new = self.chunks.new(texts)
        if new:
            first = np.zeros(len(texts), np.int64)
            first[kind[::-1]] = np.arange(len(kind))[::-1]
            first = first[new]
            inside = np.searchsorted(words, np.append(chunks, len(part)))  # the words of each chunk
            which, upto = spans(inside[first], inside[first + 1])
            ids, ends = self._from_words(column(words).take(pa.array(which)))
            ends = ends[upto]
            self.chunks.add([texts[i] for i in new], ids, np.diff(ends))
        out, upto = self.chunks.gather(texts, kind)
        return out, upto[np.searchsorted(chunks, offsets - low)]

    def _from_words(self, column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
        """Ids of all words one after the other, and where those of each begin and the last ends."""
        coded = column.dictionary_encode()
        texts = coded.dictionary.to_pylist()
        new = [texts[i] for i in self.words.new(texts)]
        if new:
            got = self.encode(new)
            self.words.add(new, np.fromiter(chain.from_iterable(got), np.int32), [len(x) for x in got])
        return self.words.gather(texts, coded.indices.to_numpy(zero_copy_only=False))


def joined(ids: np.ndarray, ends: np.ndarray, names: tuple[np.ndarray, np.ndarray]) -> tuple[bytes, np.ndarray]:
    """The names of the ids, each with the space that follows it, and where each text's names end."""
    data, at = names
    size = at[ids + 1] - at[ids]
    upto = np.concatenate([[0], np.cumsum(size)])
    return data[np.repeat(at[ids] - upto[:-1], size) + np.arange(upto[-1])].tobytes(), upto[ends]


def spelled(words: list[str]) -> tuple[np.ndarray, np.ndarray]:
    raw = [w.encode("utf-8", "replace") + b" " for w in words]
    return np.frombuffer(b"".join(raw), np.uint8), np.concatenate([[0], np.cumsum([len(r) for r in raw])])


def _rows(path: str, keep: int, what: Callable):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encoder = ChunkEncoder.of(path, keep)
        for batch in batches:
            data, offsets = utf8(batch.column("text"))
            for i, j in pieces(offsets, PIECE):
                ids, ends = encoder.run(data, offsets[i : j + 1])
                yield what(encoder, batch.slice(i, j - i), ids, ends)

    return run


def _counts(_, batch, ids, ends):
    return pa.RecordBatch.from_arrays([batch.column("doc_id"), pa.array(np.diff(ends))], names=["doc_id", "n_tokens"])


def _lists(_, batch, ids, ends):
    kept = [c for c in batch.schema.names if c != "text"]
    return pa.RecordBatch.from_arrays([*(batch.column(c) for c in kept), pa.ListArray.from_arrays(pa.array(ends.astype(np.int32)), pa.array(ids.astype(np.int32)))], names=[*kept, "ids"])


def _digests(encoder, batch, ids, ends):
    tokenizer = encoder.tokenizer
    if not hasattr(encoder, "numbers"):
        size = tokenizer.get_vocab_size()
        encoder.numbers = spelled([str(i) for i in range(size)])
        encoder.names = spelled([tokenizer.id_to_token(i) or "" for i in range(size)]) if tokenizer.decoder is None else None
    sha = lambda data, at: [hashlib.sha256(data[a : max(a, b - 1)]).hexdigest() for a, b in zip(at[:-1], at[1:], strict=True)]
    if encoder.names is not None:  # without a decoder the library joins the tokens with spaces
        back = sha(*joined(ids, ends, encoder.names))
    else:
        texts = tokenizer.decode_batch([ids[a:b].tolist() for a, b in zip(ends[:-1], ends[1:], strict=True)], skip_special_tokens=False)
        back = [hashlib.sha256(t.encode("utf-8", "replace")).hexdigest() for t in texts]
    return pa.RecordBatch.from_arrays([batch.column("doc_id"), pa.array(np.diff(ends)), pa.array(sha(*joined(ids, ends, encoder.numbers))), pa.array(back)], names=["doc_id", "n_tokens", "ids_sha256", "decoded_sha256"])


def token_counts(docs: DataFrame, path: str, keep: int = KEEP) -> DataFrame:
    """doc_id, n_tokens."""
    return mapped(docs.select("doc_id", "text"), _rows(path, keep, _counts), "doc_id long, n_tokens long")


def encode(docs: DataFrame, path: str, keep: int = KEEP) -> DataFrame:
    """The columns of docs with the text replaced by its token ids."""
    kept = [f for f in docs.schema.fields if f.name != "text"]
    schema = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in kept)
    return mapped(docs.select(*[f.name for f in kept], "text"), _rows(path, keep, _lists), f"{schema}, ids array<int>")


def encode_digests(docs: DataFrame, path: str, keep: int = KEEP) -> DataFrame:
    """doc_id, n_tokens, ids_sha256, decoded_sha256."""
    return mapped(docs.select("doc_id", "text"), _rows(path, keep, _digests), "doc_id long, n_tokens long, ids_sha256 string, decoded_sha256 string")


def decode(encoded: DataFrame, path: str) -> DataFrame:
    """doc_id and the text that the ids of encoded stand for."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        tokenizer = ChunkEncoder.of(path).tokenizer
        for batch in batches:
            ids = [x or [] for x in batch.column("ids").to_pylist()]
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), pa.array(tokenizer.decode_batch(ids, skip_special_tokens=False), pa.string())], names=["doc_id", "text"])

    return mapped(encoded.select("doc_id", "ids"), run, "doc_id long, text string")
