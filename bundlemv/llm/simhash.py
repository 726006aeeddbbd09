"""SimHash near-duplicates: 64-bit fingerprints, linked through vantage-point trees.

1. A fingerprint per document, from hashes of its word shingles (Arrow batches).
2. Equal fingerprints fold into one node each, so exact copies cost one row.
3. A vantage-point tree deals the nodes to shards. It is placed by a sample of sixteen per
   shard, and as deep as the number of nodes asks for. At each vantage
   point a node goes inside or outside a ball. By the triangle inequality only nodes
   within the link radius of the ball's surface can link across it; those also visit
   the other side, so every link lies within some shard.
4. Each shard finds its links with a vantage-point tree of its own and returns a
   spanning forest, never all pairs.
5. Components of the forests, then each document gets its component's least id.

Defined cases: null and empty texts have fingerprint zero and link like others; null ids
are kept, and a component of null ids only has a null component_id; repeated rows come
back once each; an empty table gives an empty result.
Columns beside the named ones are not read, whatever they are called; functions that
return whole rows return them as they are.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from bundlemv.llm.graphs import components, key_filter, least_by, may_hold
from bundlemv.session import materialise

SEED = 42
#: Nodes that a shard holds on average, before visitors.
SHARD_NODES = 8192
#: Fingerprints that are drawn for each shard to place vantage points (8 bytes each; the tree has 16 bytes a shard).
PER_SHARD = 16
#: Sets of up to so many nodes are compared directly.
DIRECT = 512


def shingle_hashes(data: bytes | None, shingle: int = 3, seed: int = SEED) -> np.ndarray:
    """XXH64 of all word shingles, repeats included; ASCII letters lower-cased; fewer words are one shingle."""
    words = (data or b"").lower().split()
    if not words:
        return np.zeros(0, np.uint64)
    joined = b" ".join(words)
    digest = xxhash.xxh64_intdigest
    if len(words) <= shingle:
        return np.array([digest(joined, seed)], dtype=np.uint64)
    size = np.fromiter(map(len, words), np.int64, len(words)) + 1
    after = np.cumsum(size)
    starts, ends = (after - size)[: 1 - shingle].tolist(), (after - 1)[shingle - 1 :].tolist()
    return np.array([digest(joined[a:b], seed) for a, b in zip(starts, ends)], dtype=np.uint64)


def majority(h: np.ndarray) -> int:
    """Bits that more than half of the hashes have; 0 without hashes."""
    ones = np.zeros(64, np.int64)
    for i in range(0, len(h), 1 << 16):  # little-endian bytes, so bit j of the number is column j
        ones += np.unpackbits(h[i : i + (1 << 16)].view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(axis=0, dtype=np.int64)
    return int(np.packbits(ones * 2 > len(h), bitorder="little").view(np.uint64)[0])


def text_fingerprint(data: bytes | None, shingle: int = 3, seed: int = SEED) -> int:
    return majority(shingle_hashes(data, shingle, seed))


def fingerprints(docs: DataFrame, shingle: int = 3, id_col: str = "doc_id", text_col: str = "text", seed: int = SEED) -> DataFrame:
    """id_col, fp (the fingerprint as a signed long)."""

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            fps = np.array([text_fingerprint(t.as_py(), shingle, seed) for t in b.column(1)], dtype=np.uint64).view(np.int64)
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(fps, pa.int64())], names=[id_col, "fp"])

    kind = docs.schema[id_col].dataType.simpleString()
    return docs.select(id_col, F.col(text_col).cast("binary").alias("__text")).mapInArrow(work, f"`{id_col}` {kind}, fp long")


# --- vantage-point trees -------------------------------------------------------


def distance(a, b):
    return np.bitwise_count(np.bitwise_xor(a, b)).astype(np.int16)


def build_tree(sample: np.ndarray, depth: int) -> tuple[np.ndarray, np.ndarray]:
    """A complete tree as a heap: vantage points and ball radii; node i has children 2i+1 (inside) and 2i+2."""
    points, radii = np.zeros(2**depth - 1, np.uint64), np.full(2**depth - 1, 31)
    sets = {0: sample}
    for i in range(len(points)):
        own = sets.pop(i)
        if len(own):
            spread = [int(distance(own[:256], own[j]).astype(np.int64).var() * 1000) for j in range(min(8, len(own)))]
            point = own[int(np.argmax(spread))]  # a point that tells the others apart best
            d = distance(own, point)
            radius = int(np.median(d))
            if (d <= radius).all() and radius > 0:
                radius -= 1
            points[i], radii[i] = point, radius
            sets[2 * i + 1], sets[2 * i + 2] = own[d <= radius], own[d > radius]
        else:
            sets[2 * i + 1] = sets[2 * i + 2] = own
    return points, radii


def deal(fps: np.ndarray, tree: tuple[np.ndarray, np.ndarray], reach: int) -> list[tuple[int, np.ndarray, np.ndarray]]:
    """(leaf, positions in fps, home?) - one home for each, and visits where a link may cross a surface."""
    out, stack = [], [(0, np.arange(len(fps)), np.ones(len(fps), bool))]
    while stack:
        i, at, home = stack.pop()
        if not len(at):
            continue
        if i >= len(tree[0]):
            out.append((i, at, home))
            continue
        point, radius = tree[0][i], int(tree[1][i])
        d = distance(fps[at], point)
        # Both ends of a link need not travel: of two home nodes on both sides, the outer visits the inner.
        inside = d <= radius + reach
        outside = np.where(home, d > radius, d > radius - reach)
        stack.append((2 * i + 1, at[inside], home[inside] & (d[inside] <= radius)))
        stack.append((2 * i + 2, at[outside], home[outside]))
    return out


class Forest:
    """Union-find over positions; ``edges`` holds the links that joined two trees."""

    def __init__(self, n: int):
        self.up, self.edges = list(range(n)), []

    def root(self, i: int) -> int:
        while self.up[i] != i:
            self.up[i] = i = self.up[self.up[i]]
        return i

    def link(self, i: int, j: int) -> None:
        a, b = self.root(i), self.root(j)
        if a != b:
            self.up[max(a, b)] = min(a, b)
            self.edges.append((i, j))


def link_within(fps: np.ndarray, home: np.ndarray, reach: int) -> list[tuple[int, int]]:
    """A spanning forest of all links with at least one home end, by a local vantage-point tree."""
    forest = Forest(len(fps))
    stack = [(np.arange(len(fps)), home, 0)]
    while stack:
        at, own, tried = stack.pop()
        if not own.any():
            continue
        if len(at) > DIRECT and tried < 3:
            point = fps[at[(tried * 7919) % len(at)]]
            d = distance(fps[at], point)
            radius = int(np.median(d))
            parts = []
            inside = d <= radius + reach
            outside = np.where(own, d > radius, d > radius - reach)
            parts.append((at[inside], own[inside] & (d[inside] <= radius)))
            parts.append((at[outside], own[outside]))
            if max(len(p[0]) for p in parts) < 0.8 * len(at):
                stack += [(p, o, 0) for p, o in parts]
            else:
                stack.append((at, own, tried + 1))
            continue
        mine, here = at[own], fps[at]
        for k in range(0, len(mine), 128):
            rows, cols = np.nonzero(distance(fps[mine[k : k + 128]][:, None], here[None, :]) <= reach)
            for i, j in zip(mine[k + rows].tolist(), at[cols].tolist()):
                if i != j:
                    forest.link(i, j)
    return forest.edges


def near_pairs_forest(nodes: DataFrame, reach: int, shard_nodes: int = SHARD_NODES) -> DataFrame:
    """Distinct fingerprints (fp) -> edges (u, v) that span every component of links within ``reach`` bits."""
    n = nodes.count()
    depth = max(0, math.ceil(math.log2(max(n, 1) / shard_nodes)))
    draw = nodes.select("fp").where(F.pmod(F.xxhash64("fp"), F.lit(1 << 30)) < (PER_SHARD << depth) / max(n, 1) * (1 << 30))
    sample = np.sort(draw.toArrow().column("fp").to_numpy()) if depth else np.zeros(0, np.int64)
    tree = nodes.sparkSession.sparkContext.broadcast(build_tree(np.random.default_rng(SEED).permutation(sample).view(np.uint64), depth))

    def place(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            fps = b.column(0).to_numpy(zero_copy_only=False).astype(np.int64)
            for leaf, at, home in deal(fps.view(np.uint64), tree.value, reach):
                yield pa.RecordBatch.from_arrays([pa.array(np.full(len(at), leaf), pa.int32()), pa.array(fps[at], pa.int64()), pa.array(home)], names=["leaf", "fp", "home"])

    def solve(table: pa.Table) -> pa.Table:
        fps = table.column("fp").to_numpy().astype(np.int64)
        edges = np.array(link_within(fps.view(np.uint64), table.column("home").to_numpy().astype(bool), reach), dtype=np.int64).reshape(-1, 2)
        return pa.table({"u": pa.array(fps[edges[:, 0]], pa.int64()), "v": pa.array(fps[edges[:, 1]], pa.int64())})

    placed = nodes.select("fp").mapInArrow(place, "leaf int, fp long, home boolean")
    return placed.groupBy("leaf").applyInArrow(solve, "u long, v long")


def near_duplicate_components(docs: DataFrame, reach: int = 2, shingle: int = 3, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """id_col, fp, component_id (the least id reachable over links of at most ``reach`` differing bits)."""
    prints = materialise(fingerprints(docs, shingle, id_col, text_col), "simhash")
    nodes = materialise(prints.groupBy("fp").agg(F.min(id_col).alias("least")), "simhash-nodes")
    roots = components(near_pairs_forest(nodes, reach)).withColumnRenamed("node", "fp")
    named = nodes.join(roots, "fp", "left").withColumn("root", F.coalesce("root", "fp"))
    heads = least_by(named, "root", "least", "component_id")
    labels = named.join(heads, "root").select("fp", "component_id")
    return prints.join(labels, "fp")


# --- similarity links -------------------------------------------------------------
#
# Links at a stated similarity of shingle sets, for which few differing bits are not enough:
# at a similarity of 0.8 fingerprints differ in about 10 of 64 bits, and at that radius the
# distances of a vantage point to all nodes (32, give or take 4) leave nothing to prune.
# Fingerprints of the sets are linked within few bits, through the trees, and nodes of one
# component meet first. The trees do not reach the other pairs; for those, nodes are dealt
# to shards by shared seeds as well (least values of independent hashes of their shingles;
# two texts share each with their similarity as the probability). In a component or shard,
# signatures of least values and the sizes of the sets only propose pairs; the texts of
# proposed nodes meet again under the same key, where their whole sets decide.

#: Bits within which fingerprints of sets are linked.
REACH = 2
#: Seeds per text: 1 - 0.2 ** 8 of the pairs at similarity 0.8 share one.
SEEDS = 8
#: Least values in a signature, a byte each; the estimate's deviation at 0.8 is 0.035, so the bar for proposals stands six below.
SIGNATURE, SLACK = 128, 0.215
#: A component of fingerprints, or a seed, with more texts is left out; its texts get further keys.
HOT_SEED = 20_000
#: A further key is so many bytes of the signature: 1 - 0.59 ** 30 of the pairs at similarity 0.8 share one.
BAND = 4
#: Texts that meet in a task, about, with their shingles.
SHARD_TEXTS = 2000
_MIX = np.random.default_rng(31).integers(1, 2**63, SIGNATURE, dtype=np.int64).astype(np.uint64) * np.uint64(2) + np.uint64(1)


def shingle_set(data: bytes | None, shingle: int) -> np.ndarray:
    return np.unique(shingle_hashes(data, shingle))


def signature(h: np.ndarray) -> np.ndarray:
    """Least values of SIGNATURE hashes of the shingles."""
    least = np.full(SIGNATURE, np.iinfo(np.uint64).max, np.uint64)
    for i in range(0, len(h), 512):
        x = h[i : i + 512, None] * _MIX[None, :]
        x ^= x >> np.uint64(32)
        np.minimum(least, (x * np.uint64(0xD6E8FEB86659FD93)).min(axis=0), out=least)
    return least


def sketches(docs: DataFrame, shingle: int, id_col: str, text_col: str) -> DataFrame:
    """id_col, print (a hash of the text), node (a hash of the set of shingles), fp (the set's fingerprint), size (of the set), seeds, sig."""

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            rows = []
            for t in b.column(1):
                h = shingle_set(t.as_py(), shingle)
                least = signature(h)
                sig = (least >> np.uint64(7)).astype(np.uint8).tobytes()
                rows.append((xxhash.xxh64_intdigest(h.tobytes(), SEED), majority(h), len(h), least[:SEEDS].view(np.int64).tolist() if len(h) else [], sig))
            node, fp, size, seeds, sig = zip(*rows) if rows else ((), (), (), (), ())
            node, fp = (pa.array(np.array(x, dtype=np.uint64).view(np.int64)) for x in (node, fp))
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(2), node, fp, pa.array(size, pa.int32()), pa.array(seeds, pa.list_(pa.int64())), pa.array(sig, pa.binary())], names=[id_col, "print", "node", "fp", "size", "seeds", "sig"])

    kind = docs.schema[id_col].dataType.simpleString()
    return _texts(docs, id_col, text_col).mapInArrow(work, f"`{id_col}` {kind}, print long, node long, fp long, size int, seeds array<long>, sig binary")


def _texts(docs: DataFrame, id_col: str, text_col: str) -> DataFrame:
    """id_col, text (bytes), print."""
    text = F.col(text_col).cast("binary")
    return docs.select(id_col, text.alias("__text"), F.xxhash64(text).alias("print")).toDF(id_col, "text", "print")


def texts_of(docs: DataFrame, asked: DataFrame, id_col: str, text_col: str) -> DataFrame:
    """id, print, text of the rows that ``asked`` (id, print) names, once each; only they are shuffled.

    A filter of bounded size over the prints lets the other rows go where they are read.
    """
    named = asked.select("id", "print").distinct()
    prints = materialise(named.select("print").distinct(), "sketch-prints")
    bits = docs.sparkSession.sparkContext.broadcast(key_filter(prints, "print", prints.count()))

    @F.arrow_udf("boolean")
    def maybe(x: pa.Array) -> pa.Array:
        return pa.array(may_hold(bits.value, x.to_numpy(zero_copy_only=False).astype(np.int64).view(np.uint64)))

    rows = _texts(docs, id_col, text_col).withColumnRenamed(id_col, "id").where(maybe("print"))
    rows = rows.groupBy("id", "print").agg(F.first("text").alias("text"))
    return rows.join(named, rows["id"].eqNullSafe(named["id"]) & (rows["print"] == named["print"]), "left_semi")


def proposed(size: np.ndarray, sigs: np.ndarray, seeds: np.ndarray, place: np.ndarray, similarity: float) -> np.ndarray:
    """Of the texts of one key: which have a partner that may be similar.

    place: the key's number among the seeds, or -1. A pair that shares an earlier seed is
    proposed there. A pair of two texts that are proposed already is not looked at, so a
    large group of near copies is done after its first row.
    """
    n, bar = len(size), (similarity - SLACK) * SIGNATURE
    order = np.argsort(size, kind="stable")
    size, sigs, seeds, place = size[order], sigs[order], seeds[order], place[order]
    ends = np.searchsorted(size, size / similarity + 1e-6, "right")
    flag = np.zeros(n, bool)
    for i in range(n - 1):
        at = np.arange(i + 1, ends[i])
        if flag[i]:
            at = at[~flag[at]]
        for k in range(0, len(at), 4096):
            j = at[k : k + 4096]
            j = j[(sigs[j] == sigs[i]).sum(axis=1) >= bar]
            if len(j) and (p := place[i]) > 0:
                j = j[(place[j] < 0) | (seeds[j, :p] != seeds[i, :p]).all(axis=1)]
            if len(j):
                flag[i] = flag[j] = True
    out = np.zeros(n, bool)
    out[order] = flag
    return out


def link_similar(groups: list[np.ndarray], sets: list[np.ndarray], similarity: float) -> list[tuple[int, int]]:
    """A spanning forest of the pairs within each group of positions whose sets have at least the similarity.

    Pairs that are linked already are not looked at.
    """
    forest = Forest(len(sets))
    size = np.array([len(s) for s in sets])
    starts = np.concatenate([[0], np.cumsum(size)])
    names, flat = np.unique(np.concatenate(sets), return_inverse=True) if sets else (np.zeros(0), np.zeros(0, np.int64))
    own = np.zeros(len(names), bool)
    for at in groups:
        at = at[np.argsort(size[at], kind="stable")]
        ends = np.searchsorted(size[at], size[at] / similarity + 1e-6, "right")
        label = np.array([forest.root(x) for x in at.tolist()])
        for i in range(len(at) - 1):
            near = i + 1 + np.nonzero(label[i + 1 : ends[i]] != label[i])[0]
            if not len(near):
                continue
            x = at[i]
            mine = flat[starts[x] : starts[x + 1]]
            own[mine] = True
            for j in near.tolist():
                if label[j] != label[i]:
                    y = at[j]
                    both = np.count_nonzero(own[flat[starts[y] : starts[y + 1]]])
                    if both and both / (size[x] + size[y] - both) >= similarity:
                        forest.link(int(x), int(y))
                        label[label == label[j]] = label[i]
            own[mine] = False
    return forest.edges


def _groups(key: np.ndarray) -> list[np.ndarray]:
    """Positions of each key that more than one row has."""
    order = np.argsort(key, kind="stable")
    cuts = np.nonzero(np.diff(key[order]))[0] + 1
    return [g for g in np.split(order, cuts) if len(g) > 1]


def near_first(nodes: DataFrame, reach: int) -> DataFrame:
    """``nodes`` with shingles (.., fp, .., seeds): before the seeds, a key that nodes share whose fingerprints are linked, by way of others too, within ``reach`` bits."""
    fps = materialise(nodes.where("size > 0").select("fp").distinct(), "sketch-fps")
    roots = components(near_pairs_forest(fps, reach)).withColumnRenamed("node", "fp")
    key = F.xxhash64(F.lit("fp"), F.coalesce("root", "fp"))
    return nodes.where("size > 0").join(roots, "fp", "left").withColumn("seeds", F.concat(F.array(key), "seeds")).drop("fp", "root")


def shard_keys(nodes: DataFrame) -> DataFrame:
    """node, size, seeds (what ``near_first`` puts before them among them), sig -> the same with key, place (number of the seed that is the key, or -1).

    A seed that more than HOT_SEED texts share is no key. Each text that has one gets bands
    of its signature as further keys: texts that share a passage and little else rarely share
    a band. Texts of a band that is as frequent are dealt to parts, and each two parts meet.
    """
    each = nodes.select("*", F.posexplode("seeds").alias("place", "key"))
    hot = materialise(each.groupBy("key").agg(F.count("*").alias("c")).where(F.col("c") > HOT_SEED).select("key"), "sketch-hot")
    if not hot.count():
        return each
    of_hot = materialise(each.join(hot, "key", "left_semi").select("node").distinct(), "sketch-hot-nodes")
    first, bands = SEEDS, (SIGNATURE - SEEDS) // BAND
    band = F.explode(F.array(*[F.xxhash64(F.lit(j), F.substring("sig", first + BAND * j + 1, BAND)) for j in range(bands)]))
    banded = nodes.join(of_hot, "node", "left_semi").select("*", F.lit(-1).alias("place"), band.alias("key"))
    counts = materialise(banded.groupBy("key").agg(F.count("*").alias("c")).where(F.col("c") > HOT_SEED), "sketch-hot-bands")
    parts = F.ceil(F.col("c") * 4 / HOT_SEED).cast("int")
    mine = F.pmod(F.xxhash64("node"), parts).cast("int")
    met = F.explode(F.transform(F.sequence(F.lit(0), parts - 1), lambda o: F.xxhash64("key", F.least(o, mine), F.greatest(o, mine))))
    dealt = banded.join(counts, "key").select(*nodes.columns, "place", met.alias("key"))
    calm = each.join(hot, "key", "left_anti")
    same = [*nodes.columns, "place", "key"]
    out = calm.join(of_hot, "node", "left_anti").select(same).unionAll(calm.join(of_hot, "node", "left_semi").withColumn("place", F.lit(-1)).select(same))
    return out.unionAll(banded.join(counts, "key", "left_anti").select(same)).unionAll(dealt.select(same))


def similar_components(docs: DataFrame, similarity: float = 0.8, shingle: int = 5, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """id_col, node, component_id (the least id reachable over links of at least ``similarity``)."""
    spark = docs.sparkSession
    prints = materialise(sketches(docs, shingle, id_col, text_col), "sketches")
    # a node's text is read again from the row with its least id
    nodes = materialise(prints.groupBy("node").agg(F.min(F.struct(F.col(id_col).alias("id"), "print")).alias("r"), F.min(id_col).alias("least"), F.first("fp").alias("fp"), F.first("size").alias("size"), F.first("seeds").alias("seeds"), F.first("sig").alias("sig")).select("node", "r.*", "least", "fp", "size", "seeds", "sig"), "sketch-nodes")
    n = nodes.count()
    shuffles = int(spark.conf.get("spark.sql.shuffle.partitions"))

    def propose(table: pa.Table) -> pa.Table:
        key, size, place = (table.column(c).to_numpy() for c in ("key", "size", "place"))
        sigs = np.frombuffer(b"".join(table.column("sig").to_pylist()), np.uint8).reshape(-1, SIGNATURE)
        seeds = table.column("seeds").combine_chunks().flatten().to_numpy().reshape(-1, 1 + SEEDS)
        found = np.zeros(len(key), bool)
        for at in _groups(key):
            found[at] = proposed(size[at], sigs[at], seeds[at], place[at], similarity)
        return table.select(["node", "key"]).filter(pa.array(found))

    def solve(table: pa.Table) -> pa.Table:
        node = table.column("node").to_numpy()
        names, first, of = np.unique(node, return_index=True, return_inverse=True)
        sets = [shingle_set(t.as_py(), shingle) for t in table.column("text").take(pa.array(first))]
        groups = [np.unique(of[g]) for g in _groups(table.column("key").to_numpy())]
        edges = np.array(link_similar(groups, sets, similarity), dtype=np.int64).reshape(-1, 2)
        return pa.table({"u": pa.array(names[edges[:, 0]], pa.int64()), "v": pa.array(names[edges[:, 1]], pa.int64())})

    bucket = lambda most: F.pmod(F.xxhash64("key"), F.lit(max(shuffles, most))).alias("b")
    keyed = materialise(near_first(nodes.select("node", "fp", "size", "seeds", "sig"), REACH), "sketch-keyed")
    each = shard_keys(keyed.select("node", "size", "seeds", "sig"))
    asked = each.select("node", "size", "sig", "seeds", "place", "key", bucket(-(-n * (1 + SEEDS) // 20_000))).groupBy("b").applyInArrow(propose, "node long, key long")
    asked = materialise(asked, "sketch-proposed")
    named = materialise(nodes.join(asked.select("node").distinct(), "node", "left_semi").select("node", "id", "print"), "sketch-named")
    texts = texts_of(docs, named, id_col, text_col).withColumnsRenamed({"id": "__id", "print": "__print"})
    texts = named.join(texts, F.col("print") == F.col("__print"), "inner").where(F.col("id").eqNullSafe(F.col("__id"))).select("node", "text")
    edges = asked.join(texts, "node").select("node", "key", "text", bucket(-(-asked.count() // SHARD_TEXTS))).groupBy("b").applyInArrow(solve, "u long, v long")
    roots = components(edges)
    named = nodes.select("node", "least").join(roots, "node", "left").withColumn("root", F.coalesce("root", "node"))
    heads = least_by(named, "root", "least", "component_id")
    return prints.select(id_col, "node").join(named.join(heads, "root").select("node", "component_id"), "node").select(id_col, "node", "component_id")


def fingerprint_hex(fp):
    return F.lower(F.lpad(F.hex(fp), 16, "0"))


def keep_one(docs: DataFrame, similarity: float = 0.8, shingle: int = 5, id_col: str = "doc_id") -> DataFrame:
    """The rows of ``docs`` whose id is its component's least; of repeated rows of one id, all but the first go.

    Rows with a null id have no name to be kept by; they stay.
    """
    found = similar_components(docs, similarity, shingle, id_col)
    kept = found.where(F.col(id_col) == F.col("component_id")).select(id_col).distinct()
    named = docs.where(F.col(id_col).isNotNull()).join(kept, id_col, "left_semi").dropDuplicates([id_col])
    return named.select(docs.columns).unionByName(docs.where(F.col(id_col).isNull()))


def op10(spark, sf_dir):
    from bundlemv.sources.tables import load_table

    out = near_duplicate_components(load_table(spark, sf_dir, "documents"))
    return out.select("doc_id", fingerprint_hex("fp").alias("fingerprint"), "component_id")
