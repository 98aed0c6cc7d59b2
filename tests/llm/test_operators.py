"""The ten operators against brute force, on edge cases: nulls, empty and long texts, ties, repeats, empty tables, clashing columns."""

import collections
import hashlib
import itertools
import math
import os
import random
import re
import zlib

import numpy as np
import pytest
import xxhash
from pyspark.sql import functions as F

from wordlid.llm import bpe, chat, exactdedup, fingerprint, langid, minhash, mixing, quality, sharding, tokencounts

pytest.importorskip("public_tokenizers")
from wordlid.llm.queries import tokenizer_path  # noqa: E402

SCHEMA = "doc_id long, text string, lang string, source string, n_chars long, size long, keep_id long, shard int, part int, score double"


def near(words, rng, edits):
    out = list(words)
    for i in rng.sample(range(len(out)), edits):
        out[i] = f"edit{rng.randrange(10**6)}"
    return out


@pytest.fixture(scope="module")
def rows():
    rng = random.Random(3)
    vocab = [f"w{i}" for i in range(400)]
    texts = [None, "", " ", "\t\n", "one", "one two", "One  TWO", "a b c d e", "a b c d e f", "日本語 ünï 😀 é́ x", "x" * 5000, "<|endoftext|> don't 're"]
    for _ in range(25):
        base = [rng.choice(vocab) for _ in range(rng.choice([12, 60, 150]))]
        texts.append(" ".join(base))
        for _ in range(rng.randrange(4)):
            texts.append(" ".join(near(base, rng, rng.randrange(0, 4))))
        texts.append("  ".join(base).upper() if rng.random() < 0.3 else "\n".join(base))
    hub = [rng.choice(vocab) for _ in range(150)]
    texts += [" ".join(near(hub, rng, rng.randrange(1, 5))) for _ in range(60)]  # copies of one text that is not there itself
    texts += ["the same text over and over again " * 30] * 40
    texts.append(" ".join(rng.choice(vocab) for _ in range(20000)))
    langs, sources = ["en", "fr", None], ["b", "a", None, "ä"]
    out = [(i, t, langs[i % 3], sources[i % 4] if i % 5 else "b", len(t or ""), 9, 9, 9, 9, 0.5) for i, t in enumerate(texts)]
    return [*out, out[30], out[30]]  # repeated rows


@pytest.fixture(scope="module")
def docs(spark, rows):
    return spark.createDataFrame(rows, SCHEMA).repartition(4).persist()


@pytest.fixture(scope="module")
def none(spark):
    return spark.createDataFrame([], SCHEMA)


def least_capacity(sizes, k):
    """Brute force: the least largest part of k contiguous parts."""
    upto = np.concatenate([[0], np.cumsum(sizes)])
    best = [upto[-1] - x for x in upto]
    for _ in range(k - 1):
        best = [min(max(upto[j] - upto[i], best[j]) for j in range(i, len(upto))) for i in range(len(upto))]
    return best[0]


def test_minimax_capacity_is_least():
    rng = np.random.default_rng(1)
    for t in range(120):
        n, k = int(rng.integers(1, 60)), int(rng.integers(1, 9))
        sizes = rng.integers(1, 30, n)
        if t % 3 == 0:
            sizes[rng.integers(0, n)] = rng.integers(50, 2000)
        groups = np.sort(rng.choice(np.arange(-128, 128), n, replace=False)).astype(np.int64) << 56

        def cells(inside, bits):
            c = groups[inside] >> (64 - bits)
            return [(int(x) << (64 - bits), bits, sizes[inside][c == x].sum(), (c == x).sum()) for x in np.unique(c)]

        def refine(old, at):
            parts = [cells(groups >> (64 - old.bits[i]) == old.low[i] >> (64 - old.bits[i]), min(64, int(old.bits[i]) + 2)) for i in at]
            return sharding.Cells(*zip(*sum(parts, [])))

        cuts, found = sharding.plan_shards(sharding.Cells(*zip(*cells(np.ones(n, bool), 2))), k, refine)
        edges = [0, *cuts, len(found.low)]
        assert len(cuts) < k and edges == sorted(edges)
        assert max(found.prefix[y] - found.prefix[x] for x, y in zip(edges, edges[1:])) == least_capacity(sizes, k)


@pytest.mark.parametrize("bits", [16, 2])
def test_sharding(docs, rows, none, monkeypatch, bits):
    """Two bits make cells of several groups, which have to be split."""
    monkeypatch.setattr(sharding, "UNIT_BITS", bits)
    monkeypatch.setattr(sharding, "STEP_BITS", 3)
    got = sharding.shard_documents(docs, 5).collect()
    assert len(got) == len(rows)
    text = {r[0]: r[1] or "" for r in rows}
    by_text, slots, sizes = {}, {}, {}
    for r in got:
        assert r["size"] == len(text[r["doc_id"]].encode()) + 16 and r["text_crc32"] == zlib.crc32(text[r["doc_id"]].encode())
        by_text.setdefault(text[r["doc_id"]], set()).add(r["shard"])
        slots.setdefault(r["shard"], []).append(r["slot"])
        sizes[r["shard"]] = sizes.get(r["shard"], 0) + r["size"]
    assert all(len(s) == 1 for s in by_text.values())
    assert all(sorted(s) == list(range(len(s))) for s in slots.values())
    of = {t: sum(len(t.encode()) + 16 for r in rows if (r[1] or "") == t) for t in by_text}
    order = sorted(by_text, key=lambda t: signed(xxhash.xxh64_intdigest(t.encode(), 42)))
    assert max(sizes.values()) == least_capacity(np.array([of[t] for t in order]), 5)
    placed = [min(by_text[t]) for t in order]
    assert placed == sorted(placed)  # contiguous in the order of hashes
    assert sharding.shard_documents(none, 5).count() == 0


def signed(x):
    return x - (1 << 64) if x >> 63 else x


def test_exact_duplicates(docs, rows, none):
    norm = lambda t: re.sub(r"[\x20\x09-\x0D]+", " ", t or "")
    groups = {}
    for r in rows:
        groups.setdefault(norm(r[1]), []).append(r[0])
    got = exactdedup.exact_duplicates(docs).collect()
    assert len(got) == len(rows) and sum(r["kept"] for r in got) == len(groups)
    text = {r[0]: r[1] for r in rows}
    for r in got:
        key = norm(text[r["doc_id"]])
        assert (r["keep_id"], r["group_size"], r["text_sha256"]) == (min(groups[key]), len(groups[key]), hashlib.sha256(key.encode()).hexdigest())
        assert not r["kept"] or r["doc_id"] == r["keep_id"]
    left = exactdedup.drop_exact_duplicates(docs)
    assert left.columns == docs.columns and sorted(r["doc_id"] for r in left.collect()) == sorted(min(g) for g in groups.values())
    assert exactdedup.exact_duplicates(none).count() == 0


def test_exact_duplicates_without_own_doc_id(spark):
    """A duplicate under a null or repeated doc_id takes no other text of that doc_id with it."""
    data = [(1, "copy"), (None, "copy"), (None, "alone"), (None, "alone too"), (5, "twice"), (5, "twice"), (5, "another"), (6, "twice"), (6, "third"), (None, "none"), (None, " none"), (None, " none")]
    left = exactdedup.drop_exact_duplicates(spark.createDataFrame(data, "doc_id long, text string")).collect()
    assert sorted((str(r["doc_id"]), r["text"]) for r in left) == [("1", "copy"), ("5", "another"), ("5", "twice"), ("6", "third"), ("None", " none"), ("None", "alone"), ("None", "alone too"), ("None", "none")]


def test_identifiers_that_collide(docs, spark):
    """With identifiers of two bits nearly all chunks collide, and digests tell them apart."""
    chunks = spark.createDataFrame([(1, 5), (1, 5), (2, 6), (2, 7)], "h long, d long")
    assert [r[0] for r in exactdedup.ambiguous(chunks).collect()] == [2]
    few = exactdedup.exact_duplicates(docs, lambda h: F.pmod(h, F.lit(4)))
    assert sorted(map(tuple, few.collect()), key=str) == sorted(map(tuple, exactdedup.exact_duplicates(docs).collect()), key=str)


def test_token_counts(docs, rows, none):
    from tokenizers import Tokenizer

    t = Tokenizer.from_file(tokenizer_path())
    n = [len(t.encode(r[1] or "", add_special_tokens=False).ids) for r in rows]
    hist = tokencounts.token_histogram(docs, tokenizer_path())
    for r in hist.collect():
        k = r["n_tokens"]
        assert (r["docs"], r["tokens"]) == (n.count(k), n.count(k) * k)
        assert (r["docs_ge"], r["tokens_ge"], r["truncated_tokens"]) == (sum(x >= k for x in n), sum(x for x in n if x >= k), sum(min(x, k) for x in n))
        assert r["share_le"] == pytest.approx(sum(x <= k for x in n) / len(n))
    assert tokencounts.truncated_total(hist, 77) == sum(min(x, 77) for x in n)
    assert tokencounts.quantile(hist, 0.5) == sorted(n)[(len(n) - 1) // 2]
    empty = tokencounts.token_histogram(none, tokenizer_path())
    assert empty.count() == 0 and tokencounts.quantile(empty, 0.5) is None


def test_chat(spark):
    logs = {1: ["a", "b"], 2: ["a", "b", "c"], 3: ["a", "b", "c"], 4: ["a", "x"], 5: ["b"], 6: [str(i) for i in range(600)], 7: [str(i) for i in range(300)], 8: [None, ""], 9: [""]}
    rows = [(c, i, "user" if i % 2 == 0 else None, t, 1) for c, ts in logs.items() for i, t in enumerate(ts)] + [(None, None, "user", "lone", 1)]
    got = {r["conv_id"]: r for r in chat.collapse(spark.createDataFrame(rows, "conv_id long, turn long, role string, text string, place int").repartition(5)).collect()}
    assert set(got) == {2, 4, 5, 6, 8, None}
    assert got[2]["copies"] == 2 and got[2]["rendered"] == "<|user|>\na\n<||>\nb\n<|user|>\nc\n" and got[6]["n_turns"] == 600
    assert chat.collapse(spark.createDataFrame([], "conv_id long, turn long, role string, text string")).count() == 0


def test_chat_against_brute_force(spark):
    """Random logs with many snapshots: what no longer conversation begins with stays, equal ones count."""
    rng = random.Random(11)
    logs = {}
    for c in range(120):
        if logs and rng.random() < 0.6:
            old = rng.choice(list(logs.values()))
            logs[c] = old[: rng.randrange(1, len(old) + 1)] + [(rng.choice("ua"), rng.choice(["x", "y", "", None])) for _ in range(rng.randrange(3))]
        else:
            logs[c] = [(rng.choice("ua"), rng.choice(["x", "y", None])) for _ in range(rng.randrange(1, 6))]
    plain = {c: tuple((r, t or "") for r, t in turns) for c, turns in logs.items()}
    want = {}
    for whole in set(plain.values()):
        if not any(len(o) > len(whole) and o[: len(whole)] == whole for o in plain.values()):
            same = [c for c, o in plain.items() if o == whole]
            want[min(same)] = (len(same), len(whole), "".join(f"<|{r}|>\n{t}\n" for r, t in whole))
    rows = [(c, i, r, t) for c, turns in logs.items() for i, (r, t) in enumerate(turns)]
    rng.shuffle(rows)
    got = chat.collapse(spark.createDataFrame(rows, "conv_id long, turn long, role string, text string").repartition(4)).collect()
    assert {r["conv_id"]: (r["copies"], r["n_turns"], r["rendered"]) for r in got} == want


def span_likeness(a, b):
    """Brute force of the likeness: spans as texts."""
    if a == b:
        return 1.0
    if not a or not b:
        return 0.0

    def cut(t, bits):
        out, last = [], 0
        for i in range(fingerprint.WINDOW, len(t)):
            roll = 0
            for c in t[i - fingerprint.WINDOW : i]:
                roll = (roll * int(fingerprint.ODD) + ord(c) + 1) % 2**64
            if int(fingerprint.mixed(np.array([roll], np.uint64))[0]) % (1 << bits) == 0:
                out.append(t[last:i])
                last = i
        return collections.Counter([*out, t[last:]])

    bits = max(fingerprint.level(len(a)), fingerprint.level(len(b)))
    x, y = cut(a, bits), cut(b, bits)
    common = sum(min(n, y[s]) * len(s) for s, n in x.items())
    front = len(os.path.commonprefix([a, b]))
    if len(a) < fingerprint.SHORT and len(b) < fingerprint.SHORT:
        common = max(common, front)
    elif min(len(a), len(b)) >= fingerprint.SHORT:
        common = max([common, *(k for k in (int(64 * 2 ** (i / 8)) for i in range(200)) if k <= front)])
    return common / max(len(a), len(b))


def check_fingerprints(got, data):
    """got against brute force on (doc_id, text)."""
    key = lambda r: (r[0] is not None, r[0] or 0, signed(xxhash.xxh64_intdigest((r[1] or "").encode(), 42)))
    every = sorted(data, key=key)
    texts = [r[1] or "" for r in every]
    want, prints = [], {}
    for k, ((i, _), t) in enumerate(zip(every, texts)):
        after = texts[(k + 1) % len(texts)]
        new = fingerprint.edited(t, after)
        front = lambda u: len(os.path.commonprefix([t, u]))  # noqa: B023, E731
        want.append((i, len(t), hashlib.sha256(new.encode()).hexdigest(), round(span_likeness(t, new), 9), round(span_likeness(t, after), 9), front(new), front(after)))
    have = [(r["doc_id"], r["n_chars"], r["edited_sha256"], round(r["near_edited"], 9), round(r["near_next"], 9), r["front_edited"], r["front_next"]) for r in got]
    assert sorted(have, key=str) == sorted(want, key=str)
    for r in got:
        prints.setdefault((r["n_chars"], r["fingerprint"]), r["n_chars"])
    assert len(prints) == len(set(texts))


@pytest.mark.parametrize("parts", [1, 12])
def test_fingerprints(docs, rows, none, parts):
    got = fingerprint.fingerprints(docs, parts).collect()
    check_fingerprints(got, [r[:2] for r in rows])
    assert all(r["near_edited"] >= (0.6 if r["n_chars"] > 30 else 0) for r in got)
    assert fingerprint.fingerprints(none).count() == 0


def test_fingerprints_of_large_and_missing_ids(spark):
    """Ids that floats cannot hold, null ones, and many texts under one id."""
    rng = random.Random(6)
    word = lambda: "".join(rng.choice("abcde") for _ in range(30))
    data = [(2**60 + 37 * i, word()) for i in range(400)] + [(None, word()) for _ in range(150)] + [(2**60 + 37, word()) for _ in range(150)] + [(None, None), (5, "")]
    got = fingerprint.fingerprints(spark.createDataFrame(data, "doc_id long, text string").repartition(5), 20)
    check_fingerprints(got.collect(), data)


def test_prefix_hashes_answer_spans():
    rng = random.Random(5)
    for _ in range(60):
        a, b = ("".join(rng.choice("ab😀") for _ in range(rng.randrange(1, 30))) for _ in range(2))
        x, y = fingerprint.PrefixHashes(a), fingerprint.PrefixHashes(b)
        i, j = rng.randrange(len(a)), rng.randrange(len(b))
        n = 0
        while i + n < len(a) and j + n < len(b) and a[i + n] == b[j + n]:
            n += 1
        assert x.extension(i, y, j) == n
    assert fingerprint.likeness(fingerprint.fingerprint(""), fingerprint.fingerprint("")) == 1.0
    assert fingerprint.likeness(fingerprint.fingerprint("abc"), fingerprint.fingerprint("xyz")) == 0.0


def test_scattered_edits_leave_a_text_alike():
    rng = random.Random(9)
    for n in (300, 1000, 3000):
        text = "".join(rng.choice("abcdefgh ij") for _ in range(n))
        other = list(text)
        other[n // 20] = other[n - n // 20] = "#"
        assert fingerprint.likeness(fingerprint.fingerprint(text), fingerprint.fingerprint("".join(other))) > 0.75


@pytest.mark.parametrize("name", ["word_bpe_49k.json", "byte_bpe_50k.json"])
def test_bpe_round_trip(docs, rows, none, name):
    from tokenizers import Tokenizer

    path = tokenizer_path(name)
    t = Tokenizer.from_file(path)
    text = {r[0]: r[1] or "" for r in rows}
    got = bpe.encode_digests(docs, path).collect()
    assert len(got) == len(rows)
    for r in got:
        ids = t.encode(text[r["doc_id"]], add_special_tokens=False).ids
        assert r["n_tokens"] == len(ids) and r["ids_sha256"] == hashlib.sha256(" ".join(map(str, ids)).encode()).hexdigest()
        assert r["decoded_sha256"] == hashlib.sha256(t.decode(ids, skip_special_tokens=False).encode()).hexdigest()
    if name.startswith("byte"):
        back = bpe.decode(bpe.encode(docs, path), path).collect()
        assert all(r["text"] == text[r["doc_id"]] for r in back)
    assert bpe.encode_digests(none, path).count() == 0


def test_chunks_that_are_forgotten(monkeypatch):
    """With room for a few texts only, ids stay those of the library, and texts in use are kept."""
    from tokenizers import Tokenizer

    path = tokenizer_path()
    encoder = bpe.ChunkEncoder(path, chunks=60)
    encoder.words, encoder.chunks = bpe.Memory(40), bpe.Memory(20)
    texts = [f"the same words again and number {i} of {i * i} things" for i in range(60)]
    whole = Tokenizer.from_file(path)
    for text in texts:
        data = np.frombuffer(text.encode(), np.uint8)
        ids, ends = encoder.run(data, np.array([0, len(data)]))
        assert ids.tolist() == whole.encode(text, add_special_tokens=False).ids and ends[-1] == len(ids)
        for memory in (encoder.words, encoder.chunks):
            assert len(memory.known) == len(memory.uses) == len(memory.ends) - 1 <= memory.most
    assert any(c.startswith("same") for c in encoder.words.known)


def test_wrong_joins_are_repaired():
    """Where the ids of two words together are not those of the words apart, the chunks become one, until all joins agree."""

    encoder = bpe.ChunkEncoder.__new__(bpe.ChunkEncoder)
    encoder.words = bpe.Memory(100)
    # a tokenizer for which a space between two letters a is part of a token
    encoder.seams, encoder.encode = {}, lambda texts: [[zlib.crc32(x.encode()) >> 1 for x in re.split(r"(?<!a) | (?!a)", t) if x] for t in texts]
    part = np.frombuffer(b"bb cca ad da ab xx yy za ay", np.uint8)
    starts = np.array([0, 3, 7, 10, 13, 16, 19, 22, 25])
    words, chunks = encoder.repaired(part, np.array([0]), starts, starts)
    assert words.tolist() == chunks.tolist() == [0, 3, 10, 16, 19, 22]


def test_random_texts_of_many_chunks():
    from tokenizers import Tokenizer

    rng = random.Random(4)
    for name in ("word_bpe_49k.json", "byte_bpe_50k.json"):
        encoder, whole = bpe.ChunkEncoder(tokenizer_path(name), chunks=64), Tokenizer.from_file(tokenizer_path(name))
        letters = "ab'’-.,!#0 \t\n  éß日😀\u00a0\u200d" + "etaoin" * 3
        texts = ["".join(rng.choice(letters) for _ in range(rng.randrange(0, 400))) for _ in range(300)]
        raw = [t.encode() for t in texts]
        ids, ends = encoder.run(np.frombuffer(b"".join(raw), np.uint8), np.concatenate([[0], np.cumsum([len(r) for r in raw])]))
        for k, t in enumerate(texts):
            assert ids[ends[k] : ends[k + 1]].tolist() == whole.encode(t, add_special_tokens=False).ids


def test_apportionment():
    votes = [53, 24, 23, 0, 7.5]
    for seats in range(40):
        heap = [0] * len(votes)
        for _ in range(seats):
            i = max((i for i in range(len(votes)) if votes[i] > 0), key=lambda i: (votes[i] / (2 * heap[i] + 1), -i))
            heap[i] += 1
        assert mixing.sainte_lague(votes, seats) == heap
    quotas = mixing.shard_quotas(votes, 37, 5)
    assert all(q >= 0 for s in quotas for q in s) and [sum(c) for c in zip(*quotas)] == mixing.sainte_lague(votes, 37)
    assert mixing.capped_targets([10, 10, 100], [3, 1, 2], 180) == [20.0, 20.0, 140.0]


def test_mixing(docs, rows, none):
    size = lambda t: len(re.findall(r"[^\x20\x09-\x0D]+", t or ""))
    got = mixing.mix(docs).collect()
    assert len(got) == len(rows) and sorted((r["doc_id"], r["taken"]) for r in got) == sorted((r["doc_id"], r["taken"]) for r in mixing.mix(docs.repartition(3)).collect())
    names = sorted({r[3] for r in rows if r[3] is not None}) + [None]
    sizes = [sum(size(r[1]) for r in rows if r[3] == s) for s in names]
    targets = mixing.capped_targets(sizes, [(3, 1, 2)[i % 3] for i in range(len(names))], 1.5 * sum(sizes))
    for s, n, goal in zip(names, sizes, targets):
        own = [r for r in got if r["source"] == s]
        assert all(r["source_size"] == n and r["target"] == pytest.approx(goal) and 0 <= r["taken"] <= 2 * r["size"] for r in own)
        assert sum(r["taken"] for r in own) == pytest.approx(goal, abs=40)
    assert mixing.mixed_documents(docs).columns == docs.columns
    assert mixing.mix(none).count() == 0
    brute_mix(docs, rows, targets, names, sizes)


def brute_mix(docs, rows, targets, names, sizes, block=16, shards=7):
    """Lists each source's blocks, as often as they are picked, and deals them to shards by their quotas."""
    order = {s: docs.filter(F.col("source").eqNullSafe(s)).select("doc_id", F.size(F.regexp_extract_all(F.coalesce("text", F.lit("")), F.lit(r"[^\x20\x09-\x0D]+"), F.lit(0))).alias("size"), F.xxhash64(F.lit(42), "doc_id", F.crc32("text")).alias("key")) for s in names}
    quotas = mixing.shard_quotas(targets, round(sum(targets) / block), shards)
    want = []
    for i, s in enumerate(names):
        own = sorted((((r["key"] % 1024), r["key"], r["doc_id"], r["size"]) for r in order[s].collect()))
        n = max(1, -(-sizes[i] // block))
        total = min(2 * n, sum(q[i] for q in quotas))
        phase = (42 * 2654435761 + i * 40503) % n
        picks = [total // n + ((b + 1) * (total % n) + phase) // n - (b * (total % n) + phase) // n for b in range(n)]
        assert sum(picks) == total
        ends, done = list(itertools.accumulate(q[i] for q in quotas)), 0
        shard_of = []  # of each block's first and last pick
        for p in picks:
            shard_of.append((sum(e <= done for e in ends), sum(e <= done + p - 1 for e in ends)))
            done += p
        at = 0
        for _, _, doc, size in own:
            got = [b // block for b in range(at, at + size) if picks[b // block]]
            want.append((doc, sum(picks[b] for b in got), shard_of[got[0]][0] if got else None, shard_of[got[-1]][1] if got else None))
            at += size
    have = [(r["doc_id"], r["taken"], r["first_shard"], r["last_shard"]) for r in mixing.mix(docs, shards=shards).collect()]
    assert sorted(have, key=str) == sorted(want, key=str)


def test_mixed_documents_without_own_doc_id(spark):
    """Rows under one doc_id, null or not, are taken each by its own words; repeated rows keep their number."""
    data = [(None, "", "s"), (None, "a b c", "s"), (None, "d e f", "s"), (1, "g h", "s"), (1, "i j", "s"), (2, "k l", "s"), (2, "k l", "s")]
    docs = spark.createDataFrame(data, "doc_id long, text string, source string")
    got = collections.Counter((r["doc_id"], r["text"]) for r in mixing.mixed_documents(docs, share=2.0, block=1).collect())
    assert got == {(None, "a b c"): 2, (None, "d e f"): 2, (1, "g h"): 2, (1, "i j"): 2, (2, "k l"): 4}


def brute(rows, percent):
    sets = {}
    for r in rows:
        w = re.findall(r"[^\x20\x09-\x0D]+", re.sub("[A-Z]", lambda m: m[0].lower(), r[1] or ""))
        sets[r[0]] = {tuple(w[i : i + 5]) for i in range(len(w) - 4)} if len(w) >= 5 else ({tuple(w)} if w else set())
    root = {i: i for i in sets}

    def find(i):
        while root[i] != i:
            i = root[i]
        return i

    ids = sorted(sets)
    for k, a in enumerate(ids):
        for b in ids[k + 1 :]:
            i = len(sets[a] & sets[b])
            if i and 100 * i >= percent * (len(sets[a]) + len(sets[b]) - i):
                x, y = sorted((find(a), find(b)))
                root[y] = x
    return {i: (len(sets[i]), find(i)) for i in ids}


@pytest.mark.parametrize("percent", [85, 60])
def test_near_duplicates(docs, rows, none, percent):
    want = brute(rows, percent)
    got = minhash.near_duplicates(docs, percent, bands=40, rows=4 if percent == 85 else 2).collect()
    assert len(got) == len(rows)
    for r in got:
        assert (r["n_shingles"], r["component_id"]) == want[r["doc_id"]] and r["kept"] == (r["doc_id"] == r["component_id"])
    assert minhash.near_duplicates(none, percent).count() == 0


def test_language_id(spark, docs, none):
    rng = random.Random(1)
    parts = {"x": "ka lo mi re".split(), "y": "shu ten vor gah".split()}
    data = [(i, " ".join("".join(rng.choice(parts[k]) for _ in range(3)) for _ in range(30)), k) for i in range(80) for k in (("x", "y")[i % 2],)]
    known = spark.createDataFrame(data, "doc_id long, text string, lang string")
    model = langid.train(known)
    got = langid.classify(known, model).collect()
    assert all(r["lang_pred"] == data[r["doc_id"]][2] and 0.5 <= r["score"] <= 1 and r["accepted"] for r in got)
    odd = {r["doc_id"]: r for r in langid.classify(docs, model).collect()}
    assert odd[0]["lang_pred"] == odd[1]["lang_pred"] == odd[3]["lang_pred"] == "und" and odd[0]["score"] == 0
    far = spark.createDataFrame([(1, "Привет как дела сегодня " * 20, None), (2, None, None)], "doc_id long, text string, lang string")
    assert langid.keep_identified(far, model).count() == 0
    assert langid.classify(none, langid.train(none)).count() == 0
    assert {r["lang_pred"] for r in langid.classify(known, langid.train(none)).collect()} == {"und"}


def test_language_of_few_long_texts(spark):
    """A language is learned from pieces of its texts: whole texts would be drawn or not, and a budget passed or not, by chance."""
    rng = random.Random(8)
    write = lambda letters, n: " ".join("".join(rng.choice(letters) for _ in range(4)) for _ in range(n))
    data = [(i, write("abcdefgh", 40_000), "aa") for i in range(3)] + [(10 + i, write("efghijkl", 20), "bb") for i in range(300)]
    data += [(None, write("uvwxyz", 40_000), "cc"), (None, "qrst", "dd")]
    docs = spark.createDataFrame(data, "doc_id long, text string, lang string").repartition(3)
    model = langid.train(docs, budget=20_000)
    assert model.langs == ["aa", "bb", "cc", "dd"]
    assert all(m.logp[0].max() > m.floor + 0.1 for m in model.models)  # each has counts
    tests = [write(x, 20) for x in ("abcdefgh", "efghijkl", "uvwxyz") for _ in range(20)]
    names, _, ok = model.predict(tests)
    assert names == ["aa"] * 20 + ["bb"] * 20 + ["cc"] * 20 and ok.all()


def test_language_models_and_limit_come_from_all_text(spark, monkeypatch):
    """Every n-gram of every labelled text counts, and every piece of a text is a window of the limit, however much text a language has."""
    rng = random.Random(9)
    write = lambda n: " ".join("".join(rng.choice("abcdefghij") for _ in range(rng.randrange(2, 9))) for _ in range(n))
    data = [(i, write(1_500), "aa") for i in range(60)] + [(100, "kkkkk lllll", "aa"), (101, write(50), "bb"), (102, write(60), "bb")]
    seen = []
    monkeypatch.setattr(langid, "fit", lambda model, *rest: seen.append(rest))
    model = langid.train(spark.createDataFrame(data, "doc_id long, text string, lang string").repartition(3))
    for lang, one in zip(model.langs, model.models, strict=True):
        hashes, _ = langid.counted([t for _, t, x in data if x == lang], langid.ORDER)
        assert sorted(one.keys[-1].tolist()) == sorted(hashes[:, langid.ORDER - 1].tolist())
    _, length, _, _, n = seen[0]
    whole = n[length == length.max()].sum()
    of = lambda lang: sum(math.ceil(len(t) / langid.DRAWN) for _, t, x in data if x == lang)
    assert of("aa") <= whole <= of("aa") + of("bb")  # both texts of bb may be in one half, of which the other has no model


def test_a_large_model_is_whole(spark, monkeypatch):
    """A model that does not fit at once says of all texts what it says if it does: no n-gram is left out."""
    rng = random.Random(11)
    write = lambda letters, n: " ".join("".join(rng.choice(letters) for _ in range(rng.randrange(1, 9))) for _ in range(n))
    alphabets = {"aa": "abcdefgh", "bb": "efghijkl", "cc": "xyz"}
    data = [(i, write(alphabets[x], 60), x) for i in range(90) for x in (("aa", "bb", "cc")[i % 3],)] + [(None, None, "aa"), (200, "?!", None)]
    docs = spark.createDataFrame(data, "doc_id long, text string, lang string").repartition(3)
    whole = langid.train(docs)
    monkeypatch.setattr(langid, "MOST_MODEL", 24 * langid.ORDER * 2_000)
    monkeypatch.setattr(langid, "TOGETHER", 5_000)
    large = langid.train(docs)
    tests = [write(x, n) for x in ("abcdefghijkl", "xyzabc", "qrst") for n in (1, 3, 40)]
    for one, other in zip(large.entropies(tests), whole.entropies(tests), strict=True):
        assert one == pytest.approx(other, rel=1e-5)
    assert (large.langs, large.scale, large.mean, large.spread) == (whole.langs, whole.scale, pytest.approx(whole.mean, rel=1e-6), pytest.approx(whole.spread, rel=1e-4))
    got, want = ({(r["doc_id"], r["lang_pred"], r["accepted"]): r["score"] for r in langid.classify(docs, m).collect()} for m in (large, whole))
    assert len(got) == len(data) and got == pytest.approx(want, rel=1e-4)
    assert langid.keep_identified(docs, large).count() == langid.keep_identified(docs, whole).count() == 90
    assert len(large.parts) > 3 and sum(len(p.value.keys) for p in large.parts) == len(whole.keys)


def test_windows_cover_all_text():
    """A passage counts for the limit wherever it stands in a piece, and each piece counts alike whatever its windows."""
    rng = random.Random(10)
    write = lambda letters, n: "".join(rng.choice(letters) for _ in range(n))
    model = langid.build(["aa"], [langid.counted([write("abcd", 2_000)], langid.ORDER)])
    odd = write("abcd", 112) + write("uvwxyz", 16) + write("abcd", 172)
    kinds, n = langid._windows(model, np.zeros(2, np.int64), [odd, write("abcd", 16)], np.zeros(len(langid.SCALES)))
    short = kinds >> 40 == 0
    best = (kinds[short] & 0xFFFFF) / langid.STEPS
    assert n[short][best > 4].sum() == langid.WHOLE // 18  # one of the 18 windows of 16 in 300 characters
    assert n[kinds >> 40 == 1].sum() == langid.WHOLE // 9 * 9 and langid.WHOLE * 1.9 < n[short].sum() <= langid.WHOLE * 2


def naive_kneser_ney(texts, order, vocab):
    """Interpolated Kneser-Ney from its definition: n-grams as strings, "^" before a text's first symbol."""
    folded = [" " + re.sub(" +", " ", "".join(c.lower() if c.isalpha() else " " for c in t)).lstrip(" ") for t in texts]
    tops = collections.Counter(("^" * order + t)[i + 1 : i + order + 1] for t in folded for i in range(1, len(t)))
    counts = [tops]
    for n in range(order - 1, 0, -1):
        counts.insert(0, collections.Counter(g[-n:] for g in counts[0]))
    discounts = []
    for c in counts:
        ones, twos = sum(v == 1 for v in c.values()), sum(v == 2 for v in c.values())
        discounts.append(min(0.95, max(0.1, ones / (ones + 2 * twos) if ones else 0.5)))

    def p(history, symbol):
        n = len(history)
        lower = p(history[1:], symbol) if n else 1 / (2 + vocab)
        same = {g: v for g, v in counts[n].items() if g[:-1] == history}
        if not same:
            return lower
        total = sum(same.values())
        return max(same.get(history + symbol, 0) - discounts[n], 0) / total * (history + symbol in same) + discounts[n] * len(same) / total * lower

    def entropy(text):
        t = " " + re.sub(" +", " ", "".join(c.lower() if c.isalpha() else " " for c in text)).lstrip(" ")
        logs = [math.log(p(("^" * order + t)[i + 1 : i + order], t[i])) for i in range(1, len(t))]
        return -sum(logs) / max(1, len(logs))

    return p, entropy, {g for g in counts[0]}


def test_kneser_ney_against_its_definition():
    rng = random.Random(2)
    write = lambda letters, n: " ".join("".join(rng.choice(letters) for _ in range(rng.randrange(1, 5))) for _ in range(n))
    for order in (1, 2, 3, 5):
        texts = {"x": [write("abcd", 30), write("abé", 9), "b"], "y": [write("cdefg", 25)]}
        alphabets = {x: naive_kneser_ney(t, order, 1)[2] for x, t in texts.items()}
        vocab = len(set.union(*alphabets.values()))
        model = langid.build(list(texts), [langid.counted(t, order) for t in texts.values()], order)
        tests = ["abba cab", "zzz", "A!b  c", "gdec fed", write("abcdefgz", 12)]
        cross, _ = model.entropies(tests)
        for k, t in enumerate(texts.values()):
            p, entropy, symbols = naive_kneser_ney(t, order, vocab)
            assert cross[:, k] == pytest.approx([entropy(x) for x in tests], rel=1e-5)
            history = "^" * max(0, order - 2) + " " if order > 1 else ""
            # what is left for symbols that are in no text
            assert sum(p(history, s) for s in symbols) <= 1 + 1e-9


def test_rejection_is_calibrated(spark):
    rng = random.Random(3)
    syllables = {"x": "ka lo mi re tu sa".split(), "y": "shu ten vor gah bri".split()}
    write = lambda k: " ".join("".join(rng.choice(syllables[k]) for _ in range(rng.randrange(1, 4))) for _ in range(rng.choice([3, 20, 200])))
    known = [(i, write(k), k) for i in range(300) for k in ("xy"[i % 2],)]
    model = langid.train(spark.createDataFrame(known, "doc_id long, text string, lang string"))
    assert np.mean(model.predict([write("xy"[i % 2]) for i in range(2000)])[2]) >= 0.999
    other = ["".join(rng.choice("qwzjpcfñ ") for _ in range(n)) for n in (40, 100, 400) for _ in range(100)]
    assert np.mean(model.predict(other)[2]) <= 0.05


def test_quality(spark, docs, none):
    rng = random.Random(2)
    data = [(i, " ".join(rng.choice(["good", "plain", "words"]) + ("%%%" if i % 3 == 0 else "") for _ in range(rng.randrange(1, 60)))) for i in range(400)]
    texts = spark.createDataFrame(data, "doc_id long, text string")
    labels = spark.createDataFrame([(i, int(i % 3 > 0)) for i in range(0, 400, 2)], "doc_id long, quality int")
    model = quality.train(texts, labels)
    got = quality.classify(texts, model).collect()
    assert sum((r["score"] >= 0.5) == (r["doc_id"] % 3 > 0) for r in got) >= 396
    x = np.random.default_rng(0).random((600, 2))
    y = ((x[:, 0] > 0.5) ^ (x[:, 1] > 0.5)).astype(float)
    pad = np.zeros((600, len(quality.FEATURES)))
    pad[:, :2] = x
    assert (((quality.Additive().fit(pad, y, pairs=1).score(pad) > 0.5) == y).mean()) > 0.85  # only a pair can tell
    assert all(0 <= r["score"] <= 1 for r in quality.classify(docs, model).collect())
    assert quality.classify(none, model).count() == 0
    assert {r["score"] for r in quality.classify(texts, quality.train(none, labels.limit(0))).collect()} == {0.5}


def naive_tree(residual, hessian, leaves):
    """All ways to cut ordered bins, one best cut at a time."""
    cuts = [0, len(residual)]
    value = lambda a, b: sum(residual[a:b]) / (sum(hessian[a:b]) + 1)
    worth = lambda c: sum(sum(residual[a:b]) ** 2 / (sum(hessian[a:b]) + 1) for a, b in zip(c, c[1:]))
    for _ in range(leaves - 1):
        options = [(worth(sorted([*cuts, k])), -k) for k in range(1, len(residual)) if k not in cuts]
        if not options or max(options)[0] - worth(cuts) <= 1e-9:
            break
        cuts = sorted([*cuts, -max(options)[1]])
    return [value(a, b) for a, b in zip(cuts, cuts[1:]) for _ in range(a, b)]


def test_additive_model_against_its_definition():
    """Cyclic boosting of shallow trees on bins, then of the best pairs, written out by rows; scores as sums of table entries."""
    rng = np.random.default_rng(7)
    x = np.round(rng.random((150, 3)), 2)
    y = ((x[:, 0] > 0.4) ^ (x[:, 1] > 0.6)).astype(float)
    rounds, pairs, rate = 9, 2, 0.15
    model = quality.Additive().fit(x, y, rounds=rounds, rate=rate, pairs=pairs)
    cell = lambda edges, v: sum(e <= v for e in edges)
    base = math.log(y.mean() / (1 - y.mean()))
    score = [base] * len(y)
    fine = [[cell(e, v) for v in x[:, f]] for f, e in enumerate(model.edges)]
    rough = [[cell(e, v) for v in x[:, f]] for f, e in enumerate(model.coarse)]
    for f in range(3):
        assert model.edges[f].tolist() == sorted(set(np.quantile(x[:, f], [k / quality.BINS for k in range(1, quality.BINS)])))

    def step(cells, bins):
        p = [1 / (1 + math.exp(-s)) for s in score]
        r, h = [0.0] * bins, [0.0] * bins
        for c, a, b in zip(cells, y, p):
            r[c] += a - b
            h[c] += b * (1 - b)
        tree = naive_tree(r, h, 4)
        for i, c in enumerate(cells):
            score[i] += rate * tree[c]

    for _ in range(rounds):
        for f in range(3):
            step(fine[f], len(model.edges[f]) + 1)
    p = [1 / (1 + math.exp(-s)) for s in score]
    both = lambda a, b: [i * quality.PAIR_BINS + j for i, j in zip(rough[a], rough[b])]

    def gain(a, b):
        r, h = collections.Counter(), collections.Counter()
        for c, t, q in zip(both(a, b), y, p):
            r[c] += t - q
            h[c] += q * (1 - q)
        return sum(r[c] ** 2 / (h[c] + 1) for c in r)

    best = sorted(itertools.combinations(range(3), 2), key=lambda ab: -gain(*ab))[:pairs]
    assert model.pairs == best
    for _ in range(rounds // 3):
        for a, b in best:
            step(both(a, b), quality.PAIR_BINS**2)
    assert model.score(x) == pytest.approx([1 / (1 + math.exp(-s)) for s in score], rel=1e-6)


def test_measures_against_their_definition():
    """Every feature, from the text's own words and characters."""
    texts = ["", "a", "Hello, World! x x x #tag 12", "one two two  three\nfour | é日 A1$", " \t lead and trail \n\n"]
    raw = [t.encode() for t in texts]
    got = quality.measure(np.frombuffer(b"".join(raw), np.uint8), np.concatenate([[0], np.cumsum([len(r) for r in raw])]))
    for t, r, row in zip(texts, raw, got):
        words = re.findall(rb"[^\x20\x09-\x0D]+", r.lower())
        size, n = max(1, len(r)), max(1, len(words))
        share = lambda chars: sum(r.count(c.encode()) for c in chars) / size  # noqa: B023, E731
        lower, upper, wide = sum(97 <= c <= 122 for c in r), sum(65 <= c <= 90 for c in r), sum(c >= 128 for c in r)
        lengths = [len(w) for w in words]
        mean = sum(lengths) / n
        want = {
            "log_bytes": math.log1p(len(r)), "upper": upper / max(1, lower + upper + wide), "digit": share("0123456789"), "mark": share("#$%&*@^~<>{}[]=_+\\/"), "bang": share("!?"), "bar": share("|"),
            "comma_stop": share(",.;:"), "wide": wide / size, "space": share(" \t\n\x0b\x0c\r"), "line": share("\n"), "word_size": mean, "word_spread": math.sqrt(max(0, sum(x * x for x in lengths) / n - mean**2)),
            "distinct": len(set(words)) / n, "again": sum(a == b for a, b in zip(words, words[1:])) / n, "short": sum(x <= 3 for x in lengths) / n, "top_word": max(collections.Counter(words).values(), default=0) / n,
            "marked_words": sum(bool(re.search(rb"[#$%&*@^~<>{}\[\]=_+\\/!?|]", w)) for w in words) / n,
        }
        assert dict(zip(quality.FEATURES, row)) == pytest.approx(want), t


CLASHING = "doc_id long, text string, lang string, source string, n_chars long, _doc long, _text string, _sha string, _other boolean, _a long, _b long, _times long, _rows long, _copy int, _salt int, _of long, hash long, h long, row long, part long, shard int, grp long, node long, key long, mark binary, size long, label double, score double, ahead boolean, `odd name` int"


@pytest.fixture(scope="module")
def hard(spark):
    """Null and repeated doc_ids, texts of more than two million characters, ties, and columns with the names that operators use themselves."""
    rng = random.Random(12)
    word = lambda: "".join(rng.choice(("th", "er", "on", "an", "re")) for _ in range(3))
    many = [word() for _ in range(300)]
    text = lambda n: " ".join(rng.choice(many) for _ in range(n))
    big, one, two = text(310_000), text(40), text(60)
    assert len(big) > 2_000_000
    data = [(None, one), (None, one), (None, two), (None, None), (None, ""), (1, big), (2, big + " the end"), (3, big), (4, one), (4, two), (4, two), (5, one.upper()), (6, None), (6, " "), (7, text(50)), (8, "12 !!")]
    rest = (7, "t", "s", True, 1, 2, 3, 4, 5, 6, 7, 8, 9, 10, 11, 12, 13, 14, 15, bytearray(b"m"), 16, 0.5, 0.25, False, 17)
    rows = [(i, t, "en" if i != 7 else "de", "s" if i else None, len(t or ""), *rest) for i, t in data]
    return data, spark.createDataFrame(rows, CLASHING).repartition(3).persist()


def test_hard_rows_in_operators(spark, hard):
    from tokenizers import Tokenizer

    data, docs = hard
    text = lambda t: t or ""
    shards = sharding.shard_documents(docs, 3).collect()
    assert sorted((r["size"], r["text_crc32"]) for r in shards) == sorted((len(text(t).encode()) + 16, zlib.crc32(text(t).encode())) for _, t in data)
    assert all(sorted(r["slot"] for r in shards if r["shard"] == k) == list(range(sum(r["shard"] == k for r in shards))) for k in range(3))
    whole = Tokenizer.from_file(tokenizer_path())
    ids = {t: whole.encode(t, add_special_tokens=False).ids for t in {text(t) for _, t in data}}
    assert sorted((str(r["doc_id"]), r["n_tokens"], r["ids_sha256"]) for r in bpe.encode_digests(docs, tokenizer_path()).collect()) == sorted((str(i), len(ids[text(t)]), hashlib.sha256(" ".join(map(str, ids[text(t)])).encode()).hexdigest()) for i, t in data)
    assert {r["n_tokens"]: r["docs"] for r in tokencounts.token_histogram(docs, tokenizer_path()).collect()} == collections.Counter(len(ids[text(t)]) for _, t in data)
    sizes = sorted((str(r["doc_id"]), r["n_chars"]) for r in fingerprint.fingerprints(docs, 4).collect())
    assert sizes == sorted((str(i), len(text(t))) for i, t in data)
    found = langid.classify(docs, langid.train(docs)).collect()
    assert len(found) == len(data) and {r["lang_pred"] for r in found if r["doc_id"] in (6, 8)} == {"und"}
    exact = exactdedup.exact_duplicates(docs).collect()
    assert collections.Counter((r["keep_id"], r["group_size"]) for r in exact) == {(4, 3): 6, (1, 2): 2, (2, 1): 1, (5, 1): 1, (6, 3): 3, (6, 1): 1, (7, 1): 1, (8, 1): 1}
    near = minhash.near_duplicates(docs, 85).collect()
    assert collections.Counter((r["doc_id"], r["component_id"], r["kept"]) for r in near) == {(None, None, True): 5, (1, 1, True): 1, (2, 1, False): 1, (3, 1, False): 1, (4, 4, True): 3, (5, 4, False): 1, (6, 6, True): 2, (7, 7, True): 1, (8, 8, True): 1}
    taken = mixing.mix(docs).collect()
    assert len(taken) == len(data) and all(0 <= r["taken"] <= 2 * r["size"] for r in taken)
    labels = spark.createDataFrame([(i, k % 2) for k, i in enumerate([1, 2, 4, 4, 5, 7, None])], "doc_id long, quality int")
    model = quality.train(docs, labels)
    assert all(0 <= r["score"] <= 1 for r in quality.classify(docs, model).collect())


def test_hard_rows_in_stages(hard):
    """Every stage returns whole rows with all columns, whatever these are called."""
    data, docs = hard
    kept = lambda df: sorted((str(r["doc_id"]), r["text"]) for r in df.collect() if r["text"])
    names = docs.columns
    out = langid.keep_identified(docs, langid.train(docs))
    assert out.columns == names and kept(out) == sorted((str(i), t) for i, t in data if t and t != " " and "12" not in t)
    left = exactdedup.drop_exact_duplicates(docs)
    first = {}
    for i, t in data:
        first.setdefault(re.sub(r"\s+", " ", t or ""), []).append(i)
    assert left.columns == names and left.count() == len(first)
    assert sorted(str(r["doc_id"]) for r in left.collect()) == sorted(str(min((i for i in ids if i is not None), default=None)) for ids in first.values())
    alone = minhash.drop_near_duplicates(docs, 85)
    assert alone.columns == names and collections.Counter(r["doc_id"] for r in alone.collect()) == {None: 5, 1: 1, 4: 3, 6: 2, 7: 1, 8: 1}
    mixed = mixing.mixed_documents(docs)
    assert mixed.columns == names and {k for k, _ in kept(mixed)} <= {str(i) for i, _ in data}
    tokens = bpe.encode(docs, tokenizer_path())
    assert tokens.columns == [c for c in names if c != "text"] + ["ids"] and tokens.count() == len(data)


def test_pipeline(spark, tmp_path, rows):
    import corpus_pipeline

    rng = random.Random(8)
    spell = {"en": "th er on an re".split(), "de": "ch ung en zu pf".split()}
    data = []
    for i in range(120):
        lang = ("en", "de")[i % 2]
        t = " ".join("".join(rng.choice(spell[lang]) for _ in range(3)) for _ in range(80))
        data.append((i, t, lang, f"s{i % 3}", len(t)))
    data += [(200 + k, data[k][1].replace(" ", "  "), data[k][2], "s0", 0) for k in range(10)]
    for k in range(10):
        w = data[k][1].split()
        w[40] = "changed"
        data.append((300 + k, " ".join(w), data[k][2], "s1", 0))
    data += [(400, "12 34 !!", "en", "s2", 8), (401, None, None, None, None)]
    spark.createDataFrame(data, "doc_id long, text string, lang string, source string, n_chars long").write.parquet(f"{tmp_path}/documents.parquet")
    docs = spark.read.parquet(f"{tmp_path}/documents.parquet")
    kept = {}
    for k, (name, stage) in enumerate(corpus_pipeline.STAGES):
        out = stage(spark, docs, str(tmp_path))
        out.write.parquet(f"{tmp_path}/{k}")
        docs = spark.read.parquet(f"{tmp_path}/{k}")
        kept[name] = [r["doc_id"] for r in docs.collect()]
        assert name == "encode" or docs.columns == ["doc_id", "text", "lang", "source", "n_chars"]
    assert set(kept["language"]) == {r[0] for r in data} - {400, 401}
    assert set(kept["exact_dedup"]) == set(kept["language"]) - set(range(200, 210))
    assert set(kept["near_dedup"]) == set(range(120)) and len(kept["near_dedup"]) == 120
    assert 150 <= len(kept["mix"]) <= 210 and set(kept["mix"]) <= set(range(120)) and kept["encode"]
    left = {}
    assert sorted(corpus_pipeline.run(spark, str(tmp_path), left).select(F.col("doc_id")).toPandas()["doc_id"]) == sorted(kept["mix"])
    assert left == {name: len(kept[name]) for name, _ in corpus_pipeline.STAGES[:-1]}


def test_native_operators_have_no_python(docs, spark):
    """The operators that are to stay in the JVM have no Python worker in any plan, and no checkpoint that one executor holds."""
    turns = spark.createDataFrame([(1, 0, "u", "a")], "conv_id long, turn long, role string, text string")
    for df in (exactdedup.exact_duplicates(docs), exactdedup.drop_exact_duplicates(docs), chat.collapse(turns)):
        assert not re.search("Python|MapInArrow|MapInPandas|FlatMapGroups", df._jdf.queryExecution().toString())
    folder = os.path.dirname(os.path.abspath(exactdedup.__file__))
    for name in os.listdir(folder):
        if name.endswith(".py"):
            code = open(os.path.join(folder, name)).read()
            assert "localCheckpoint" not in code and "crossJoin" not in code
            if name in ("exactdedup.py", "chat.py"):
                assert not re.search(r"udf|InArrow|InPandas|\.rdd", code)
