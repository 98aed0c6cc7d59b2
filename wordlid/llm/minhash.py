"""Near-duplicates by one-permutation hashing with optimal densification.

A document's set of word n-grams is hashed once; the hash range is split into bins, the smallest
value of each bin is its sketch, and an empty bin takes the value of the first non-empty one that its own fixed
random sequence of bins names. Bands of bins give bucket keys. In each bucket only edges from its
smallest document to the others are candidates (a star), and every candidate is confirmed on the full
sets. A bucket whose members are still in different components is looked at again: n-grams that few of its documents have give
their pairs at once and settle, by an exact bound, every document that has too few others; what is left open meets further centres,
ever more of them, until the bucket holds one component or every member has been a centre, so no link between
two members of a bucket is lost to the star; pairs inside one component are never compared again.

Documents with equal sets are one class with one representative, so copies make no pairs. Rows of a class, bucket, component or
document that has more than a thousandth of all rows are dealt over several tasks.

Nulls: a null or wordless text has an empty set and is linked with nothing; a null doc_id is never linked.
Rows that share a doc_id and their set count as one document; rows that share a doc_id with other sets are documents
of their own. An empty table gives an empty result; extra columns are ignored, whatever their names.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from wordlid.io import cut_lineage, discard
from wordlid.llm.arrowtext import mapped, mixed, pieces, shingles, utf8
from wordlid.llm.hot import MOST_SENT, sent_if_few, spread_join, unused

#: At a similarity of 0.85 a link is in none of 40 bands of 6 bins six times in 1e9, at 0.8 five times in 1e6;
#: at 0.5, where there is nothing to find, half of the pairs meet, and at 0.3, three of a hundred.
BANDS, ROWS = 40, 6
FIRST_CENTRES = 64
#: Holders up to which an n-gram is rare among the documents of unsettled buckets.
RARE = 16
#: Bits for each id of a first filter of rows, and ids up to which there is one (32 MB).
BITS_EACH, MOST_IN_BITMAP = 16, 1 << 24
#: Members of a bucket that meet a set of centres in one task.
TOGETHER = 512


def donors(bins: int, tries: int = 64) -> np.ndarray:
    """tries x bins: the bins that an empty bin asks in turn."""
    grid = np.arange(tries * bins, dtype=np.uint64).reshape(tries, bins)
    return (mixed(grid + np.uint64(0x5EED)) % np.uint64(bins)).astype(np.int64)


def sketch(values: np.ndarray, bins: int, ask: np.ndarray) -> np.ndarray:
    """The densified one-permutation sketch of a sorted, non-empty set of 64-bit hashes."""
    step = np.uint64(2**64 // bins + 1)
    edges = np.arange(bins, dtype=np.uint64) * step
    at = np.searchsorted(values, edges)
    low = values[np.minimum(at, len(values) - 1)]
    full = (at < len(values)) & ((low // step) == np.arange(bins, dtype=np.uint64))
    out, empty = low.copy(), np.flatnonzero(~full)
    for k in range(len(ask)):
        if not len(empty):
            return out
        asked = ask[k][empty]
        ok = full[asked]
        out[empty[ok]] = low[asked[ok]]
        empty = empty[~ok]
    if len(empty):  # after so many tries: the next full bin round the circle
        where = np.flatnonzero(full)
        out[empty] = low[where[np.searchsorted(where, empty) % len(where)]]
    return out


def band_keys(values: np.ndarray, bands: int, rows: int, ask: np.ndarray) -> np.ndarray:
    grid = sketch(values, bands * rows, ask).reshape(bands, rows)
    key = np.arange(bands, dtype=np.uint64)
    for k in range(rows):
        key = mixed(key * np.uint64(0x9E3779B97F4A7C15) + grid[:, k])
    return key.view(np.int64)


def _sketches(size: int, bands: int, rows: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        ask = donors(bands * rows)
        for batch in batches:
            data, offsets = utf8(batch.column("text"))
            for i, j in pieces(offsets):
                sets = shingles(data, offsets[i : j + 1], size)
                keys = [band_keys(s, bands, rows, ask) if len(s) else None for s in sets]
                yield pa.RecordBatch.from_arrays(
                    [batch.column("doc_id").slice(i, j - i), batch.column("hash").slice(i, j - i), pa.array([len(s) for s in sets], pa.int64()), pa.array(_marks(sets), pa.binary()), pa.array(keys, pa.list_(pa.int64()))],
                    names=["doc_id", "hash", "n", "mark", "keys"],
                )

    return run


def _marks(sets: list[np.ndarray]) -> list[bytes | None]:
    return [hashlib.blake2b(s.tobytes(), digest_size=16).digest() if len(s) else None for s in sets]


def _bits(ids: np.ndarray, size: int) -> np.ndarray:
    return (mixed(ids.astype(np.int64).view(np.uint64)) % np.uint64(size)).astype(np.int64)


def _sets(size: int, bitmap):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            if bitmap is not None:
                wanted = np.frombuffer(bitmap.value, np.uint8)
                hit = _bits(batch.column("doc_id").to_numpy(zero_copy_only=False), 8 * len(wanted))
                batch = batch.take(pa.array(np.flatnonzero((wanted[hit >> 3] >> (hit & 7).astype(np.uint8)) & 1)))
            data, offsets = utf8(batch.column("text"))
            for i, j in pieces(offsets):
                sets = shingles(data, offsets[i : j + 1], size)
                ends = np.concatenate([[0], np.cumsum([len(s) for s in sets])]).astype(np.int32)
                flat = np.concatenate([*sets, np.zeros(0, np.uint64)]).view(np.int64)
                yield pa.RecordBatch.from_arrays([batch.column("doc_id").slice(i, j - i), pa.array(_marks(sets), pa.binary()), pa.ListArray.from_arrays(pa.array(ends), pa.array(flat))], names=["doc_id", "mark", "items"])

    return run


def _bitmap_of(ids: DataFrame, many: int) -> bytes:
    """One bit for each hashed doc_id, in a map of BITS_EACH bits for each of them."""
    size = max(1 << 18, 1 << (many * BITS_EACH - 1).bit_length())

    def run(batches):
        for batch in batches:
            hit = np.unique(_bits(batch.column("doc_id").to_numpy(zero_copy_only=False), size))
            yield pa.RecordBatch.from_arrays([pa.array(hit + 1)], names=["bit"])

    bits = mapped(ids, run, "bit long")
    parts = bits.groupBy(F.bitmap_bucket_number("bit").alias("b")).agg(F.bitmap_construct_agg(F.bitmap_bit_position("bit")).alias("m")).collect()
    out = np.zeros(size // 8, np.uint8)
    for r in parts:  # buckets count from 1 and hold 32768 values each
        first = (r["b"] - 1) * 4096
        out[first : first + 4096] |= np.frombuffer(bytes(r["m"]), np.uint8)
    return out.tobytes()


def _of(sets: DataFrame, nodes: DataFrame) -> DataFrame:
    """The sets of these nodes; without a shuffle of the others where the nodes, counted first, are few."""
    return sets.join(sent_if_few(nodes), "node", "left_semi")


def confirm(pairs: DataFrame, sets: DataFrame, percent: int) -> DataFrame:
    """The pairs a, b whose full sets have 100 * intersection >= percent * union. A node may be `a`, a centre, in any number of pairs;
    it is `b` in no more than the buckets it is in have centres."""
    pairs = cut_lineage(pairs, "pairs")
    total = pairs.count()
    sets = _of(sets, pairs.select(F.explode(F.array("a", "b")).alias("node")).distinct())
    both = spread_join(pairs.join(sets.toDF("b", "y"), "b"), sets.toDF("a", "x"), "a", pairs.groupBy("a").agg(F.count("*").alias("n")), total)
    both = both.select("a", "b", F.size(F.array_intersect("x", "y")).alias("i"), (F.size("x") + F.size("y")).alias("s"))
    out = cut_lineage(both.filter(F.col("i") * 100 >= (F.col("s") - F.col("i")) * percent).select("a", "b"), "links")
    discard(pairs)
    return out


def components(links: DataFrame) -> DataFrame:
    """node, root: the smallest node reachable, for every node with an edge.

    Each round links every node's larger neighbours to its smallest one, then its smaller ones too, until
    the edges are stars; each round is written out. Rounds grow with the logarithm of the longest path.
    """
    edges = cut_lineage(links.select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v")).filter("u <> v").distinct(), "edges")
    while True:
        many = edges.count()
        both = edges.union(edges.select("v", "u")).toDF("u", "v")
        least = cut_lineage(both.groupBy("u").agg(F.min("v").alias("m"), F.count("*").alias("n")).select("u", F.least("u", "m").alias("m"), "n"), "least")
        large = cut_lineage(spread_join(both, least.drop("n"), "u", least.select("u", "n"), 2 * many).filter("v > u").select(F.col("v").alias("u"), F.col("m").alias("v")).filter("u <> v").distinct(), "large")
        small = cut_lineage(large.groupBy("u").agg(F.min("v").alias("m"), F.count("*").alias("n")), "small")
        hung = spread_join(large, small.drop("n"), "u", small.select("u", "n"), many)
        hung = hung.select(F.explode(F.array(F.struct(F.col("v").alias("u"), F.col("m").alias("v")), F.struct(F.col("u"), F.col("m").alias("v")))).alias("e")).select("e.*")
        old, edges = edges, cut_lineage(hung.filter("u <> v").distinct(), "edges")
        discard(old, least, large, small)
        # stars: no node hangs on two others, none that others hang on hangs itself
        ends = edges.select(F.col("u").alias("x"), F.lit(1).alias("hangs"), F.lit(0).alias("holds")).union(edges.select("v", F.lit(0), F.lit(1)))
        loose = F.col("hangs") + F.least("holds", F.lit(1))
        if ends.groupBy("x").agg(F.sum("hangs").alias("hangs"), F.sum("holds").alias("holds")).filter((F.col("hangs") > 0) & (loose > 1)).isEmpty():
            return edges.select(F.col("u").alias("node"), F.col("v").alias("root"))


def _several(rows: DataFrame, name: str) -> DataFrame:
    """rows (key, root, ...) of the keys with several roots, and how many rows their key has."""
    rows = cut_lineage(rows, name)
    found = cut_lineage(rows.groupBy("key").agg(F.min("root").alias("r"), F.max("root").alias("s"), F.count("*").alias("many")).filter("r <> s").select("key", "many"), "keys")
    if found.count() <= MOST_SENT:  # then the rows stay where they are, and no key is hot
        out = rows.join(F.broadcast(found), "key")
    else:
        out = spread_join(rows, found, "key", found.select("key", F.col("many").alias("n")), rows.count())
    out = cut_lineage(out, name)
    discard(rows, found)
    return out


def _still_open(open_: DataFrame, roots: DataFrame) -> DataFrame:
    """The same after further links: turns stay, keys that hold one component by now go."""
    rest = [c for c in open_.columns if c not in ("root", "many")]
    named = open_.join(roots.withColumnRenamed("root", "new"), "node", "left").select(*rest, F.coalesce("new", "root").alias("root"))
    return _several(named, "open")


def _torn(members: DataFrame, roots: DataFrame, sets: DataFrame, percent: int) -> tuple[DataFrame, DataFrame]:
    """The members of buckets that hold more than one component, if they can still have a link there; and pairs to confirm at once.

    N-grams that at most RARE of these documents have are set apart. Two documents that share some of those are a
    pair, and there are few for each n-gram. Two that share none have at most the smaller of their counts of other n-grams
    (`shared`) in common, and a document whose whole count falls short of the similarity is settled and goes.
    """
    named = members.join(roots, "node", "left").select("key", "node", F.coalesce("root", "node").alias("root"))
    torn = _several(named, "torn")
    nodes = cut_lineage(torn.select("node", "root").distinct(), "nodes")
    mine = _of(sets, nodes.select("node"))
    items = mine.select("node", F.explode("items").alias("item"))
    # an n-gram that more have is counted, never gathered: its few smallest holders are all that the aggregate carries
    rare = cut_lineage(items.groupBy("item").agg(F.count("*").alias("holders"), F.min("node").alias("low"), F.max("node").alias("high")).filter(F.col("holders") <= RARE), "rare")
    two = rare.filter("holders <= 2").select("item", "holders", F.explode(F.array_distinct(F.array("low", "high"))).alias("node"))
    more = items.join(rare.filter("holders > 2").select("item", "holders"), "item").select("item", "holders", "node")
    held = cut_lineage(two.unionByName(more), "held")
    own = held.groupBy("node").agg(F.count("*").alias("own"))
    sizes = mine.select("node", F.size("items").alias("n"))
    reach = cut_lineage(nodes.join(own, "node", "left").join(sizes, "node").withColumn("shared", F.col("n") - F.coalesce("own", F.lit(0))), "reach")
    twice = held.filter("holders > 1")
    met = twice.select("item", F.col("node").alias("a")).join(twice.select("item", F.col("node").alias("b")), "item").filter("a < b").groupBy("a", "b").agg(F.count("*").alias("k"))
    side = lambda x: reach.select(F.col("node").alias(x), *[F.col(c).alias(f"{x}_{c}") for c in ("root", "n", "shared")])
    most = F.least("a_shared", "b_shared") + F.col("k")
    near = met.join(side("a"), "a").join(side("b"), "b").filter((F.col("a_root") != F.col("b_root")) & (most * 100 >= (F.col("a_n") + F.col("b_n") - most) * percent))
    near = cut_lineage(near.select("a", "b"), "near")
    left = torn.drop("root", "many").join(reach.filter(F.col("shared") * 100 >= F.col("n") * percent), "node").select("key", "node", "root", "n", "shared")
    open_ = _several(left, "open")
    own = open_.groupBy("node", "root", "n", "shared").agg(F.collect_list(F.struct("key", "many")).alias("in"))  # at most one for each band
    each = own.select("node", "root", "n", "shared", F.col("in.key").alias("keys"), F.explode("in").alias("at"))
    out = cut_lineage(each.select("at.key", F.pmod(F.xxhash64("at.key", "node"), "at.many").alias("turn"), "at.many", "node", "root", "n", "shared", "keys"), "open")
    discard(torn, nodes, rare, held, reach, open_)
    return out, near


def _crossing(open_: DataFrame, low: int, high: int, percent: int) -> DataFrame:
    """Pairs of a bucket's centres of these turns with its members of other components and later turns, where a link is possible.

    The members of a large bucket are dealt over tasks, TOGETHER to each, and its centres go to all of them.
    """
    salts = F.floor(F.col("many") / TOGETHER).cast("int") + 1
    members = open_.withColumn("salt", F.pmod(F.xxhash64("node"), salts).cast("int"))
    centres = open_.filter((F.col("turn") >= low) & (F.col("turn") < high)).select(F.explode(F.sequence(F.lit(0), salts - 1)).alias("c_salt"), *[F.col(x).alias(f"c_{x}") for x in ("key", "node", "root", "n", "shared", "keys", "turn")])
    reach = F.least("shared", "c_shared")
    can = (F.col("c_root") != F.col("root")) & (reach * 100 >= (F.col("n") + F.col("c_n") - reach) * percent)
    can = can & (F.struct("c_turn", "c_node") < F.struct("turn", "node"))  # not once more from the other side
    can = can & (F.col("key") == F.array_min(F.array_intersect("keys", "c_keys")))  # once, in the first bucket that both are in
    return members.join(centres, (F.col("key") == F.col("c_key")) & (F.col("salt") == F.col("c_salt")) & can).select(F.col("c_node").alias("a"), F.col("node").alias("b")).distinct()


def _linked(docs: DataFrame, percent: int, size: int, bands: int, rows: int) -> DataFrame:
    """doc_id, hash (of the text), n_shingles, component_id, kept."""
    texts = docs.select("doc_id", "text")
    base = cut_lineage(mapped(texts.withColumn("hash", F.xxhash64("text")), _sketches(size, bands, rows), "doc_id long, hash long, n long, mark binary, keys array<long>"), "sketches")
    marked = base.filter("mark is not null and doc_id is not null")
    repeated = cut_lineage(marked.groupBy("doc_id").agg(F.count("*").alias("n"), (F.min("mark") != F.max("mark")).alias("other")).filter("n > 1"), "repeated")
    twice = repeated.filter("other").select("doc_id", F.lit(True).alias("_twice"))
    torn_ids = not twice.isEmpty()

    def noded(df: DataFrame) -> DataFrame:
        """A node is a doc_id, or where a doc_id has several sets, a hash of it and the set."""
        if not torn_ids:
            return df.withColumn("node", F.col("doc_id"))
        return df.join(twice, "doc_id", "left").withColumn("node", F.when(F.col("_twice"), F.xxhash64("doc_id", "mark")).otherwise(F.col("doc_id"))).drop("_twice")

    # equal sets have equal keys, so any will do
    classes = cut_lineage(noded(marked.groupBy("mark").agg(F.min("doc_id").alias("doc_id"), F.count("*").alias("copies"), F.any_value("keys").alias("keys"))), "classes")
    base, wide = cut_lineage(base.drop("keys"), "marks"), base
    heads = classes.select("node", F.explode("keys").alias("key"))
    buckets = cut_lineage(heads.groupBy("key").agg(F.count("*").alias("many"), F.min("node").alias("centre")).filter("many > 1"), "buckets")
    members = cut_lineage(spread_join(heads, buckets, "key", buckets.select("key", F.col("many").alias("n")), classes.count() * bands), "members")
    classes, wide_classes = cut_lineage(classes.drop("keys"), "classes"), classes
    discard(wide, wide_classes, buckets)
    held = cut_lineage(classes.select("node", "doc_id", "mark").join(members.select("node").distinct(), "node", "left_semi"), "held")
    many, bitmap, some = held.count(), None, texts.filter("doc_id is not null")
    if many <= MOST_IN_BITMAP:
        bitmap = docs.sparkSession.sparkContext.broadcast(_bitmap_of(held.select("doc_id"), max(many, 1)))
    else:
        some = some.join(held.select("doc_id").distinct(), "doc_id", "left_semi")
    sets = mapped(some, _sets(size, bitmap), "doc_id long, mark binary, items array<long>")
    if torn_ids:
        sets = sets.join(held, ["doc_id", "mark"]).select("node", "items")
    else:
        sets = sets.filter("mark is not null").select(F.col("doc_id").alias("node"), "items")
    if not repeated.isEmpty():
        sets = sets.dropDuplicates(["node"])
    sets = cut_lineage(sets, "sets")
    tried = members.filter("node <> centre").select(F.col("centre").alias("a"), F.col("node").alias("b")).distinct()
    links = confirm(tried, sets, percent)
    roots = components(links)
    open_, near = _torn(members, roots, sets, percent)
    more = confirm(near.union(_crossing(open_, 0, FIRST_CENTRES, percent)).distinct(), sets, percent)
    discard(near, members)
    low = FIRST_CENTRES
    while True:  # until every member has been a centre
        if not more.isEmpty():  # what these links join needs no further look
            links = cut_lineage(links.union(more), "links")
            roots = components(links)
            open_ = _still_open(open_, roots)
        most = open_.agg(F.max("turn")).first()[0]
        if most is None or low > most:
            break
        more = confirm(_crossing(open_, low, low * 8, percent), sets, percent)
        low *= 8
    discard(held, sets, open_, links, more, repeated if not torn_ids else None)
    named = classes.join(roots, "node", "left").select("mark", "doc_id", "copies", F.coalesce("root", "node").alias("root"))
    if torn_ids:
        named = named.join(named.groupBy("root").agg(F.min("doc_id").alias("least")), "root").withColumn("root", F.col("least"))
    named = cut_lineage(named.filter("copies > 1 or root <> doc_id").select("mark", "root", F.col("copies").alias("n")), "named")
    out = base.select("doc_id", "hash", F.col("n").alias("n_shingles"), F.when(F.col("doc_id").isNotNull(), F.col("mark")).alias("mark"))
    out = spread_join(out, named.drop("n"), "mark", named.select("mark", "n"), base.count(), "left")
    component = F.coalesce("root", "doc_id")
    return out.select("doc_id", "hash", "n_shingles", component.alias("component_id"), component.eqNullSafe(F.col("doc_id")).alias("kept"))


def near_duplicates(docs: DataFrame, percent: int = 85, size: int = 5, bands: int = BANDS, rows: int = ROWS) -> DataFrame:
    """doc_id, n_shingles, component_id (smallest doc_id reachable by links), kept."""
    return _linked(docs, percent, size, bands, rows).select("doc_id", "n_shingles", "component_id", "kept")


def drop_near_duplicates(docs: DataFrame, percent: int = 80, size: int = 5, bands: int = BANDS, rows: int = ROWS) -> DataFrame:
    """The rows of docs that stay, one document of each component, with all their columns. Rows are told apart by doc_id and text together."""
    doc, text = unused(docs, "_doc", "_text")
    gone = cut_lineage(_linked(docs, percent, size, bands, rows).filter("not kept").select(F.col("doc_id").alias(doc), F.col("hash").alias(text)).distinct(), "gone")
    return docs.join(sent_if_few(gone), (F.col("doc_id") == F.col(doc)) & (F.xxhash64("text") == F.col(text)), "left_anti")
