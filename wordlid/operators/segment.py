"""Sub-words: byte-pair merges and a unigram model, learned from word frequencies."""

from __future__ import annotations

import heapq
import math
from collections import Counter, defaultdict

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from wordlid.io import bound_batches, cut_lineage, discard

#: Types up to which the driver holds them all, in arrays of some forty bytes a letter, and merges pair by pair; beyond, pairs are counted and
#: merged in Spark, some at a time. Every type counts either way.
DRIVER_TYPES = 4_000_000
MARK = "\u2581"
#: Different words whose pieces a worker remembers.
REMEMBERED = 200_000


def counted(types: DataFrame) -> list[tuple[str, int]]:
    return [(r["word"], r["n"]) for r in types.select("word", "n").filter("length(word) > 0").orderBy(F.desc("n"), "word").toLocalIterator()]


def learn_merges(types: DataFrame, merges: int, driver_types: int = DRIVER_TYPES) -> list[tuple[str, str]]:
    """Byte-pair merges of all types (word, n)."""
    if types.count() <= driver_types:
        rows = types.select("word", "n").filter("length(word) > 0").toArrow()
        return train_bpe_arrays(rows["word"].to_pylist(), rows["n"].to_numpy(), merges)
    return train_bpe_spark(types, merges, max(1, merges // 200))


def _merged(seq: list[str], pair: tuple[str, str]) -> list[str]:
    k, out = 0, []
    while k < len(seq):
        if k + 1 < len(seq) and seq[k] == pair[0] and seq[k + 1] == pair[1]:
            out.append(seq[k] + seq[k + 1])
            k += 2
        else:
            out.append(seq[k])
            k += 1
    return out


def _merging(sent):
    """A function that merges the pairs in sent, in their order, in each of some sequences."""

    def apply(seqs: pd.Series) -> pd.Series:
        def one(seq):
            out = list(seq)
            for pair in sent.value:
                out = _merged(out, pair)
            return out

        return seqs.map(one)

    return apply


def train_bpe_spark(types: DataFrame, merges: int, together: int = 1) -> list[tuple[str, str]]:
    """The same with the types where they are: each round counts all adjacent pairs, and merges the most frequent ones that share no
    piece, `together` at the most. With one at a time the merges are those of train_bpe."""
    spark = types.sparkSession
    seqs = cut_lineage(types.filter("length(word) > 1").select(F.filter(F.split("word", ""), lambda c: c != "").alias("seq"), "n"), "bpe")
    out: list[tuple[str, str]] = []
    while len(out) < merges:
        at = F.sequence(F.lit(0), F.size("seq") - 2)
        adjacent = seqs.filter("size(seq) > 1").select("n", F.explode(F.transform(at, lambda i: F.struct(F.get("seq", i).alias("l"), F.get("seq", i + 1).alias("r")))).alias("p"))
        top = adjacent.groupBy("p.l", "p.r").agg(F.sum("n").alias("n")).filter("n > 1").orderBy(F.desc("n"), "l", "r").limit(4 * together).collect()
        chosen, used = [], set()
        for r in top:
            if len(chosen) == min(together, merges - len(out)) or used & {r["l"], r["r"]}:
                break
            chosen.append((r["l"], r["r"]))
            used |= {r["l"], r["r"]}
        if not chosen:
            break
        apply = _merging(spark.sparkContext.broadcast(chosen))
        old, seqs = seqs, cut_lineage(seqs.select(F.pandas_udf(apply, "array<string>")("seq").alias("seq"), "n"), "bpe")
        discard(old)
        out += chosen
    discard(seqs)
    return out


def train_tokenizer(words: DataFrame, pieces: int = 10_000) -> list[tuple[str, int, float]]:
    """piece, id, score of a tokenizer learned from the words (word, n) of raw sentences: each begins with a mark, so that texts can be put
    together again. Ids are from 3 (0 pads, 1 is unknown, 2 ends a sentence); letters come first, a merge's score is its rank with a minus."""
    marked = words.select(F.concat(F.lit(MARK), "word").alias("word"), "n")
    letters = [r["c"] for r in marked.select(F.explode(F.array_distinct(F.filter(F.split("word", ""), lambda c: c != ""))).alias("c")).distinct().orderBy("c").collect()]
    merges = learn_merges(marked, max(0, pieces - 3 - len(letters)))
    table = [*[(c, 0.0) for c in letters], *[(a + b, -1.0 - i) for i, (a, b) in enumerate(merges)]]
    known: dict[str, float] = {}
    for piece, score in table:
        known.setdefault(piece, score)
    return [(piece, i + 3, score) for i, (piece, score) in enumerate(known.items())]


def split_scored(word: str, scores: dict[str, float]) -> list[str]:
    """Pieces of a marked word: the neighbours whose joined piece has the best score become one, again and again."""
    s = list(word)
    while len(s) > 1:
        best = max(((scores.get(a + b, -math.inf), -k) for k, (a, b) in enumerate(zip(s, s[1:], strict=False))), default=(-math.inf, 0))
        if best[0] == -math.inf:
            break
        k = -best[1]
        s[k : k + 2] = [s[k] + s[k + 1]]
    return s


def tokenize(df: DataFrame, column: str, table: list[tuple[str, int, float]]) -> Column:
    """Pieces of all words of a text."""
    bound_batches(df.sparkSession)
    sent = df.sparkSession.sparkContext.broadcast({p: s for p, _, s in table})

    def pieces(texts: pd.Series) -> pd.Series:
        known: dict[str, list[str]] = {}

        def one(text):
            out = []
            for w in (text or "").split():
                if w not in known:
                    known[w] = split_scored(MARK + w, sent.value)
                out += known[w]
            return out

        return texts.map(one)

    return F.pandas_udf(pieces, "array<string>")(column)


def decode(pieces: Column) -> Column:
    """The text that pieces of a tokenizer stand for."""
    return F.ltrim(F.translate(F.array_join(pieces, ""), MARK, " "))


def train_bpe(words: list[tuple[str, int]], merges: int) -> list[tuple[str, str]]:
    """Merge the most frequent adjacent pair again and again, ties to the smaller pair; only words with the pair are touched."""
    seqs, counts = [list(w) for w, _ in words], [n for _, n in words]
    uses, where = Counter(), defaultdict(set)
    for i, s in enumerate(seqs):
        for p in zip(s, s[1:], strict=False):
            uses[p] += counts[i]
            where[p].add(i)
    heap = [(-n, p) for p, n in uses.items()]
    heapq.heapify(heap)
    out: list[tuple[str, str]] = []
    while heap and len(out) < merges:
        n, pair = heapq.heappop(heap)
        if -n != uses[pair]:
            if uses[pair] > 0:
                heapq.heappush(heap, (-uses[pair], pair))
            continue
        if uses[pair] < 2:
            break
        out.append(pair)
        touched = set()
        for i in where.pop(pair):
            s = seqs[i]
            for p in zip(s, s[1:], strict=False):
                uses[p] -= counts[i]
                touched.add(p)
            k, new = 0, []
            while k < len(s):
                if k + 1 < len(s) and (s[k], s[k + 1]) == pair:
                    new.append(s[k] + s[k + 1])
                    k += 2
                else:
                    new.append(s[k])
                    k += 1
            seqs[i] = new
            for p in zip(new, new[1:], strict=False):
                uses[p] += counts[i]
                where[p].add(i)
                touched.add(p)
        uses[pair] = 0
        for p in touched:
            if uses[p] > 0:
                heapq.heappush(heap, (-uses[p], p))
    return out


def train_bpe_arrays(words: list[str], counts: np.ndarray, merges: int) -> list[tuple[str, str]]:
    """The merges of train_bpe, over all letters in one array: the places of a pair are found, merged and counted anew at once."""
    codes = np.frombuffer("".join(words).encode("utf-32-le", "surrogatepass"), np.uint32)
    sizes = np.array([len(w) for w in words], np.int64)
    kinds, symbol = np.unique(codes, return_inverse=True)
    names = [chr(c) for c in kinds.tolist()]
    ids = {c: i for i, c in enumerate(names)}
    most = np.int64(len(names) + merges + 1)
    symbol = symbol.astype(np.int32)
    after, before = np.arange(1, len(codes) + 1, dtype=np.int32), np.arange(-1, len(codes) - 1, dtype=np.int32)
    ends = np.cumsum(sizes[sizes > 0])
    after[ends - 1] = -1
    before[ends - sizes[sizes > 0]] = -1
    word = np.repeat(np.arange(len(words), dtype=np.int32), sizes)
    counts = np.asarray(counts, np.int64)
    uses: dict[int, int] = {}
    where: defaultdict[int, list[np.ndarray]] = defaultdict(list)

    def pairs_at(left: np.ndarray) -> np.ndarray:
        return symbol[left] * most + symbol[after[left]]

    def grouped(keys: np.ndarray, left: np.ndarray) -> list[tuple[int, int, np.ndarray]]:
        """Each pair with its uses and its places."""
        if not len(keys):
            return []
        order = np.argsort(keys, kind="stable")
        keys, left = keys[order], left[order]
        first = np.flatnonzero(np.append(True, keys[1:] != keys[:-1]))
        sums = np.add.reduceat(counts[word[left]], first)
        return list(zip(keys[first].tolist(), sums.tolist(), np.split(left, first[1:]), strict=True))

    named = lambda key: (names[key // int(most)], names[key % int(most)])
    left = np.flatnonzero(after >= 0).astype(np.int32)
    for key, n, places in grouped(pairs_at(left), left):
        uses[key] = n
        where[key].append(places)
    heap = [(-n, named(key), key) for key, n in uses.items()]
    heapq.heapify(heap)
    out: list[tuple[str, str]] = []
    while heap and len(out) < merges:
        n, pair, key = heapq.heappop(heap)
        if -n != uses[key]:
            if uses[key] > 0:
                heapq.heappush(heap, (-uses[key], pair, key))
            continue
        if uses[key] < 2:
            break
        out.append(pair)
        a, b = divmod(key, int(most))
        at = np.sort(np.concatenate(where.pop(key)))
        at = at[(symbol[at] == a) & (after[at] >= 0)]
        at = at[symbol[after[at]] == b]
        if a == b and len(at):  # of a run every other one, from its beginning
            first = np.append(True, at[1:] != after[at[:-1]])
            place = np.arange(len(at))
            at = at[(place - np.maximum.accumulate(np.where(first, place, 0))) % 2 == 0]
        gone = after[at]
        ahead, behind = before[at], after[gone]
        # a pair between two merged ones goes and comes once, as the one ahead of the later
        chosen = lambda x: symbol[x] == -2
        old_left, old_right = ahead[ahead >= 0], gone[behind >= 0]
        lost = [(pairs_at(old_left), old_left)]
        old = pairs_at(old_right)
        symbol[at] = -2
        apart = ~chosen(after[old_right])
        lost.append((old[apart], old_right[apart]))
        lost = grouped(np.concatenate([x for x, _ in lost]), np.concatenate([y for _, y in lost]))
        joined = ids.setdefault(pair[0] + pair[1], len(names))
        if joined == len(names):
            names.append(pair[0] + pair[1])
        symbol[gone] = -1
        after[at] = behind
        before[behind[behind >= 0]] = at[behind >= 0]
        ahead = before[at]
        new_left, new_right = ahead[ahead >= 0], at[behind >= 0]
        new_right = new_right[~chosen(after[new_right])]
        symbol[at] = joined
        left = np.concatenate([new_left, new_right])
        touched = set()
        for k, less, _ in lost:
            uses[k] -= less
            touched.add(k)
        for k, more, places in grouped(pairs_at(left), left):
            uses[k] = uses.get(k, 0) + more
            where[k].append(places)
            touched.add(k)
        uses[key] = 0
        for k in touched:
            if uses[k] > 0:
                heapq.heappush(heap, (-uses[k], named(k), k))
    return out


def split_bpe(word: str, ranks: dict[tuple[str, str], int]) -> list[str]:
    s = list(word)
    while len(s) > 1:
        best = min(((ranks.get(p, math.inf), k) for k, p in enumerate(zip(s, s[1:], strict=False))), default=(math.inf, 0))
        if best[0] == math.inf:
            break
        pair, k, new = (s[best[1]], s[best[1] + 1]), 0, []
        while k < len(s):
            if k + 1 < len(s) and (s[k], s[k + 1]) == pair:
                new.append(s[k] + s[k + 1])
                k += 2
            else:
                new.append(s[k])
                k += 1
        s = new
    return s


def encode_bpe(df: DataFrame, merges: list[tuple[str, str]]) -> Column:
    """Pieces of the column word; merges are bounded by the vocabulary and sent once."""
    bound_batches(df.sparkSession)
    sent = df.sparkSession.sparkContext.broadcast({p: i for i, p in enumerate(merges)})

    def pieces(words: pd.Series) -> pd.Series:
        return words.map(lambda w: split_bpe(w or "", sent.value))

    return F.pandas_udf(pieces, "array<string>")("word")


def encode_unigram(df: DataFrame, logp: dict[str, float]) -> Column:
    """Pieces of the column word: its likeliest split."""
    bound_batches(df.sparkSession)
    sent = df.sparkSession.sparkContext.broadcast(logp)

    def pieces(words: pd.Series) -> pd.Series:
        return words.map(lambda w: split_unigram(w or "", sent.value))

    return F.pandas_udf(pieces, "array<string>")("word")


def train_unigram(words: list[tuple[str, int]], size: int, rounds: int = 4, longest: int = 8, seeds: int = 4) -> dict[str, float]:
    """Log-probabilities of pieces: EM over all splits, then the least useful pieces go until `size` are left."""
    uses: Counter = Counter()
    for w, n in words:
        for i in range(len(w)):
            for j in range(i + 1, min(len(w), i + longest) + 1):
                uses[w[i:j]] += n
    letters = {c for w, _ in words for c in w}
    top = sorted((p for p in uses if len(p) > 1), key=lambda p: (-uses[p] * len(p), p))[: seeds * size]
    logp = {p: float(uses[p]) for p in [*letters, *top]}
    total = sum(logp.values())
    logp = {p: math.log(v / total) for p, v in logp.items()}
    for r in range(rounds):
        expected: defaultdict[str, float] = defaultdict(float)
        for w, n in words:
            for p, v in _posterior(w, logp, longest).items():
                expected[p] += n * v
        logp = _kept_pieces(expected, letters, size if r == rounds - 1 else max(size, int(len(expected) * 0.6)))
    return logp


def train_unigram_spark(types: DataFrame, size: int, rounds: int = 4, longest: int = 8, seeds: int = 4) -> dict[str, float]:
    """The same over all types (word, n) where they are: seeds by an aggregation of all substrings, expected uses by tasks, and sums of
    them by piece; the driver holds the pieces, some times `size`."""
    bound_batches(types.sparkSession)
    words = cut_lineage(types.select("word", "n").filter("length(word) > 0"), "unigram")
    starts = F.sequence(F.lit(1), F.length("word"))
    cuts = F.flatten(F.transform(starts, lambda i: F.transform(F.sequence(F.lit(1), F.least(F.lit(longest), F.length("word") - i + 1)), lambda k: F.substring("word", i, k))))
    uses = words.select("n", F.explode(cuts).alias("piece")).groupBy("piece").agg(F.sum("n").alias("n"))
    uses = cut_lineage(uses, "unigram")
    letters = {r["piece"]: r["n"] for r in uses.filter("length(piece) = 1").collect()}
    top = uses.filter("length(piece) > 1").orderBy(F.desc(F.col("n") * F.length("piece")), "piece").limit(seeds * size).collect()
    mass = {k: float(v) for k, v in letters.items()} | {r["piece"]: float(r["n"]) for r in top}
    discard(uses)
    logp = _normalised(mass)
    for r in range(rounds):
        sent = words.sparkSession.sparkContext.broadcast(logp)

        def expect(batches, sent=sent):
            for b in batches:
                total: defaultdict[str, float] = defaultdict(float)
                for w, n in zip(b["word"], b["n"], strict=True):
                    for p, v in _posterior(w, sent.value, longest).items():
                        total[p] += n * v
                yield pd.DataFrame({"piece": list(total), "uses": list(total.values())})

        got = words.mapInPandas(expect, "piece string, uses double").groupBy("piece").agg(F.sum("uses").alias("uses")).collect()
        expected = {x["piece"]: x["uses"] for x in got}
        logp = _kept_pieces(expected, set(letters), size if r == rounds - 1 else max(size, int(len(expected) * 0.6)))
    discard(words)
    return logp


def _normalised(mass: dict[str, float]) -> dict[str, float]:
    total = sum(mass.values())
    return {p: math.log(v / total) for p, v in mass.items()}


def _kept_pieces(expected: dict[str, float], letters: set[str], keep: int) -> dict[str, float]:
    """Letters, and the longer pieces with the most expected uses."""
    kept = sorted((p for p in expected if len(p) > 1), key=lambda p: (-round(expected[p], 6), p))[: max(0, keep - len(letters))]
    return _normalised({p: expected.get(p, 0.0) + 1e-3 for p in [*sorted(letters), *kept]})


def _posterior(w: str, logp: dict[str, float], longest: int) -> dict[str, float]:
    """Expected uses of each piece over all splits of a word."""
    n = len(w)
    ahead, back = [1.0] + [0.0] * n, [0.0] * n + [1.0]
    for j in range(1, n + 1):
        ahead[j] = sum(ahead[i] * math.exp(logp[w[i:j]]) for i in range(max(0, j - longest), j) if w[i:j] in logp)
    for i in range(n - 1, -1, -1):
        back[i] = sum(back[j] * math.exp(logp[w[i:j]]) for j in range(i + 1, min(n, i + longest) + 1) if w[i:j] in logp)
    out: defaultdict[str, float] = defaultdict(float)
    if ahead[n] > 0:
        for i in range(n):
            for j in range(i + 1, min(n, i + longest) + 1):
                if w[i:j] in logp:
                    out[w[i:j]] += ahead[i] * math.exp(logp[w[i:j]]) * back[j] / ahead[n]
    return out


def split_unigram(word: str, logp: dict[str, float], longest: int = 8) -> list[str]:
    """The most likely split; an unknown letter is a piece of its own."""
    best: list[tuple[float, int]] = [(0.0, 0)]
    for j in range(1, len(word) + 1):
        best.append(max((best[i][0] + logp.get(word[i:j], -30.0 if j - i == 1 else -math.inf), i) for i in range(max(0, j - longest), j)))
    out, j = [], len(word)
    while j:
        out.append(word[best[j][1] : j])
        j = best[j][1]
    return out[::-1]


def piece_ids(df: DataFrame, column: str, merges: list[tuple[str, str]], vocab: dict[str, int]) -> Column:
    """Ids of the pieces of all words of a text, each word's first piece marked by the word separator; 1 is unknown."""
    bound_batches(df.sparkSession)
    sent = df.sparkSession.sparkContext.broadcast(({p: i for i, p in enumerate(merges)}, vocab, {}))

    def ids(texts: pd.Series) -> pd.Series:
        ranks, number, known = sent.value  # a worker keeps the words that it knows from batch to batch

        def one(text: str) -> list[int]:
            out = []
            for w in (text or "").split():
                if w not in known:
                    if len(known) >= REMEMBERED:
                        known.clear()
                    known[w] = [2] + [number.get(p, 1) for p in split_bpe(w, ranks)]
                out += known[w]
            return out

        return texts.map(one)

    return F.pandas_udf(ids, "array<int>")(column)


def vocabulary(types: DataFrame, merges: list[tuple[str, str]]) -> dict[str, int]:
    """Ids from 3 of the letters of all types and of the merges; 0 pads, 1 is unknown, 2 begins a word."""
    letters = types.select(F.explode(F.array_distinct(F.filter(F.split("word", ""), lambda c: c != ""))).alias("c")).distinct().orderBy("c").collect()
    return {p: i + 3 for i, p in enumerate(dict.fromkeys([*(r["c"] for r in letters), *(a + b for a, b in merges)]))}
