"""SimHash near-duplicates with BK-tree shards.

Fingerprints: each word shingle votes with the 64 bits of its XXH64; a bit is set if more than half of the votes have it.
Wider fingerprints join several seeds. Candidates meet in shards whose keys are parts of the fingerprint:

* `block_layout`: the bits are cut in blocks; two fingerprints that differ in at most `radius` bits agree on some
  blocks - radius whole blocks, so one shard per choice of blocks loses no link (`linked`, the op10 contract). Of those
  blocks the key takes as many bits as give shards of about PER_TREE rows, so keys follow the number of rows.
* `sampled_keys`: keys of key_bits randomly chosen bits, with as many tables as the wanted recall at the wanted similarity
  takes (`near_duplicates`); both follow from the number of rows, so recall is the same at every size.

`linked`: every shard is a BK-tree (`Trees`; a node's children are keyed by their integer Hamming distance to it). All
fingerprints of the shard search it from the root and follow only edges within the radius of their own distance. A tree
meets its queries by the shard key instead of being broadcast: fingerprints of all documents must not pass the driver. A
shard above CHUNK rows is cut into chunks; each pair of chunks is a task of its own, so hot shards spread and nothing is
capped. A shard reports a spanning forest, never all pairs of a dense group.

`near_duplicates`: the radius there (47 of 192 bits) is wider than the spread of distances, so hardly an edge can be left
out and nodes of LEAF rows or fewer are compared directly. Its links need a check, so a shard first reports a few pairs of
each row of a dense group; then an exact prefix-filter join over the shingle sets of all rows of such groups finds the pairs
that the verified links have not joined, so no pair is left out.

Components come from a distributed iteration over written tables; driver memory holds nothing that grows with documents.

Defined edge results: null and empty texts have no words and fingerprint zero; they are linked like any other row, all
rows of one fingerprint being one node (so a doc_id that stands for several texts joins nothing). Ids may be null: such a
row takes the component of its fingerprint if another row of it has an id, else null. Repeated rows stay repeated. Empty
tables give empty results. Only id and text are read, so other columns may have any name.
"""

from __future__ import annotations

import math
from collections.abc import Iterator
from itertools import combinations

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import as_bytes, blank_words, free_prefix, hot_join, removed, small, written
from .components import connected_components

SEEDS = (42, 43, 44, 45)
#: Rows of one shard that one task compares; larger shards are cut into chunks of this size.
CHUNK = 2000
#: Number of hot shard keys up to which their list is broadcast (16 bytes each).
BROADCAST_KEYS = 50_000
#: Number of ids (8 bytes each) up to which a list of ids is broadcast; beyond it is joined.
BROADCAST_IDS = 1_000_000
LEAF = 32
#: Rows that a shard's BK-tree is to have on average.
PER_TREE = 256
#: Rows of whole shards whose trees are built and searched together.
TOGETHER = 1 << 16


# ---------------------------------------------------------------- fingerprints
def shingle_hashes(words: list[bytes], k: int, seed: int) -> np.ndarray:
    """XXH64 of each k-word shingle (repeats included); of the whole sequence if it is shorter; none without words."""
    if not words:
        return np.empty(0, np.uint64)
    line = b" ".join(words)
    if len(words) <= k:
        return np.array([xxhash.xxh64_intdigest(line, seed)], np.uint64)
    lengths = np.fromiter(map(len, words), np.int64, len(words)) + 1
    ends = np.cumsum(lengths) - 1
    starts = ends - lengths + 1
    digest = xxhash.xxh64_intdigest
    n = len(words) - k + 1
    return np.fromiter((digest(line[a:b], seed) for a, b in zip(starts[:n].tolist(), ends[k - 1:].tolist())), np.uint64, n)


def majority(hashes: np.ndarray) -> int:
    """Bits set in over half of the hashes, as an unsigned integer."""
    total = np.zeros(64, np.int64)
    for at in range(0, len(hashes), 1 << 16):
        part = np.ascontiguousarray(hashes[at:at + (1 << 16)])
        total += np.unpackbits(part.view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(0, dtype=np.int64)
    return int(np.packbits(2 * total > len(hashes), bitorder="little").view(np.uint64)[0]) if len(hashes) else 0


def fingerprints(docs: DataFrame, words: int = 4, bits: int = 64, lower: bool = True, shingles: bool = False,
                 distinct: bool = False) -> DataFrame:
    """docs (doc_id, text) -> doc_id, mark (hash of the text), f0..f(bits/64-1) signed longs, seq (hash of the word
    sequence), and with `shingles` the sorted distinct low 32 bits of the shingle hashes. If `distinct`, a repeated shingle
    votes once."""
    seeds = SEEDS[: bits // 64]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in small(batches):
            prints, seqs, sets = [[] for _ in seeds], [], []
            for t in as_bytes(b.column(1)):
                ws = blank_words(t.lower() if lower else t) if t else []
                for k, s in enumerate(seeds):
                    h = shingle_hashes(ws, words, s)
                    prints[k].append(majority(np.unique(h) if distinct else h))
                    if not k and shingles:
                        sets.append(np.unique(h.astype(np.uint32)).view(np.int32))
                seqs.append(xxhash.xxh64_intdigest(b" ".join(ws), 7))
            cols = [b.column(0), b.column(2), *(pa.array(np.array(p, np.uint64).view(np.int64)) for p in prints), pa.array(np.array(seqs, np.uint64).view(np.int64))]
            names = ["doc_id", "mark", *(f"f{k}" for k in range(len(seeds))), "seq"]
            if shingles:
                cols.append(pa.array(sets, pa.list_(pa.int32())))
                names.append("shingles")
            yield pa.RecordBatch.from_arrays(cols, names)

    schema = "doc_id long, mark long, " + "".join(f"f{k} long, " for k in range(len(seeds))) + "seq long" + ", shingles array<int>" * shingles
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text", F.xxhash64("text").alias("mark")).mapInArrow(run, schema)


# ---------------------------------------------------------------- shard keys
def block_layout(bits: int, radius: int, rows: int, per_tree: int = PER_TREE) -> list[np.ndarray]:
    """Bit positions of each shard key: as many bits as leave about per_tree rows in a shard, taken evenly from every
    choice of blocks - radius blocks, of the fewest blocks that have so many bits. Few rows are one shard."""
    wanted = max(0, math.ceil(math.log2(max(rows, 1) / per_tree)))
    if not wanted:
        return [np.empty(0, np.int64)]
    for blocks in range(radius + 1, bits + 1):
        choices = [np.concatenate(c) for c in combinations(np.array_split(np.arange(bits), blocks), blocks - radius)]
        if min(map(len, choices)) >= min(wanted, bits // 2):
            return [c[np.linspace(0, len(c) - 1, min(wanted, len(c))).astype(np.int64)] for c in choices]
    raise ValueError("the radius is too wide for the bits")


def sampled_keys(bits: int, rows: int, differs: float, recall: float, least_bits: int = 12, per_shard: int = 1000) -> list[np.ndarray]:
    """Random bit positions: key length from the number of rows, number of tables from the recall that pairs with a
    share `differs` of differing bits are to have."""
    k = max(least_bits, math.ceil(math.log2(max(rows, 1) / per_shard)))
    tables = math.ceil(math.log(1 - recall) / math.log(1 - (1 - differs) ** k))
    rng = np.random.default_rng(20)
    return [rng.choice(bits, k, replace=False) for _ in range(tables)]


def keyed(nodes: DataFrame, keys: list[np.ndarray], width: int) -> DataFrame:
    """nodes (id, f0..) -> a row of them and `key` for each shard key. The key holds the number of its table."""
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in small(batches):
            f = [b.column(1 + w).to_numpy(zero_copy_only=False).view(np.uint64) for w in range(width)]
            for t, positions in enumerate(keys):
                key = np.zeros(len(b), np.uint64)
                for p in positions.tolist():
                    key = (key << np.uint64(1)) | ((f[p // 64] >> np.uint64(p % 64)) & np.uint64(1))
                key = key * np.uint64(len(keys)) + np.uint64(t)
                yield pa.RecordBatch.from_arrays([pa.array(key.view(np.int64)), *b.columns], ["key", *b.schema.names])

    names = [f"f{w}" for w in range(width)]
    return nodes.select("id", *names).mapInArrow(run, "key long, id long, " + ", ".join(f"{n} long" for n in names))


# ---------------------------------------------------------------- BK-trees
def distances(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    return np.bitwise_count(a ^ b).sum(-1, dtype=np.int64)


class Trees:
    """The BK-trees of shards in flat arrays: a node is a row, its children are keyed by their distance to it, and a
    shard's first row is its root. Built and searched level by level, all shards at once."""

    def __init__(self, f: np.ndarray, shard: np.ndarray):
        """f: n x words; shard: a number from 0 for each row."""
        n, self.f, self.width = len(f), f, 64 * f.shape[1] + 2
        parent, edge = np.full(n, -1), np.zeros(n, np.int64)
        self.root = np.zeros(int(shard.max()) + 1 if n else 0, np.int64)
        self.shard = shard
        rows, group, above, by = np.arange(n), shard, None, None
        while len(rows):
            groups, first, member = np.unique(group, return_index=True, return_inverse=True)
            nodes = rows[first]
            if above is None:
                self.root[groups] = nodes
            else:
                parent[nodes], edge[nodes] = above[first], by[first]
            later = np.ones(len(rows), bool)
            later[first] = False
            above, rows = nodes[member[later]], rows[later]
            by = distances(f[rows], f[above])
            group = above * self.width + by
        child = np.flatnonzero(parent >= 0)
        key = parent[child] * self.width + edge[child]
        self.child = child[np.argsort(key, kind="stable")]
        #: where the children of (node, edge) begin in `child`
        self.begin = np.r_[0, np.cumsum(np.bincount(key, minlength=n * self.width))]
        self.visited = 0

    def within(self, queries: np.ndarray, radius: int) -> Iterator[tuple[np.ndarray, np.ndarray]]:
        """(query, row) pairs of rows of one shard that differ in at most `radius` bits, the query itself included."""
        q, at = queries, self.root[self.shard[queries]]
        while len(q):
            self.visited += len(q)
            d = distances(self.f[q], self.f[at])
            hit = d <= radius
            yield q[hit], at[hit]
            base = at * self.width
            lo = self.begin[base + np.maximum(d - radius, 0)]
            n = self.begin[base + np.minimum(d + radius, self.width - 2) + 1] - lo
            ends = np.cumsum(n)
            at = self.child[np.repeat(lo - ends + n, n) + np.arange(ends[-1])]
            q = np.repeat(q, n)

    def stars(self, radius: int) -> tuple[np.ndarray, np.ndarray]:
        """A spanning star (member, root) of each group of rows that are linked within the radius."""
        root = np.arange(len(self.f))
        step = max(64, (1 << 20) // max(1, int(np.bincount(self.shard).max()) if len(self.shard) else 1))
        for at in range(0, len(root), step):
            found = [(q[q > r], r[q > r]) for q, r in self.within(np.arange(at, min(at + step, len(root))), radius)]
            root = merge(root, np.concatenate([q for q, _ in found]), np.concatenate([r for _, r in found]))
        member = np.flatnonzero(root != np.arange(len(root)))
        return member, root[member]


def close_pairs(f: np.ndarray, radius: int) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """Pairs i < j of rows of f (n x words) within the radius, block by block.

    All rows query one BK-tree together: a node is a pivot, its children hold the rows at one integer distance from it,
    and of the queries only those whose own distance to the pivot is within the radius of that integer follow.
    """
    stack = [(np.arange(len(f)), np.arange(len(f)))]
    while stack:
        rows, queries = stack.pop()
        if len(rows) <= LEAF:
            for at in range(0, len(queries), 4096):
                q = queries[at:at + 4096]
                i, j = np.nonzero((distances(f[q][:, None], f[rows][None]) <= radius) & (q[:, None] < rows[None]))
                if len(i):
                    yield q[i], rows[j]
            continue
        pivot, rest = rows[0], rows[1:]
        to_query, to_rest = distances(f[queries], f[pivot]), distances(f[rest], f[pivot])
        hit = queries[(to_query <= radius) & (queries != pivot)]
        if len(hit):
            yield np.minimum(hit, pivot), np.maximum(hit, pivot)
        order = np.argsort(to_rest, kind="stable")
        edges, at = np.unique(to_rest[order], return_index=True)
        for d, child in zip(edges.tolist(), np.split(rest[order], at[1:])):
            follow = queries[np.abs(to_query - d) <= radius]
            if len(follow):
                stack.append((child, follow))


def merge(root: np.ndarray, i: np.ndarray, j: np.ndarray) -> np.ndarray:
    """Unites the groups of i and j; root[x] is the smallest member of x's group."""
    while True:
        a, b = root[i], root[j]
        open_ = a != b
        if not open_.any():
            return root
        lo, hi = np.minimum(a[open_], b[open_]), np.maximum(a[open_], b[open_])
        first = np.full(len(root), len(root))
        np.minimum.at(first, hi, lo)
        root = np.where(first < len(root), np.minimum(first, root), root)
        while not np.array_equal(again := root[root], root):
            root = again


def witnesses(f: np.ndarray, radius: int, small: int = 16) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Pairs to be verified first, and the rows of groups of which not all pairs are among them: all pairs of a group of
    up to `small` rows; in a denser group each row with its nearest row and with the row nearest to the group's majority
    fingerprint."""
    root, a, b = np.arange(len(f)), [], []
    kept = 0
    for i, j in close_pairs(f, radius):
        root = merge(root, i, j)
        if kept <= small * len(f):
            a.append(i), b.append(j)
            kept += len(i)
    if not a:
        return np.empty(0, int), np.empty(0, int), np.empty(0, int)
    i, j = np.concatenate(a), np.concatenate(b)
    size = np.bincount(root, minlength=len(f))
    few = size[root[i]] <= small
    left, right = [i[few]], [j[few]]
    dense = (size > small) | ((size > 1) & (kept > small * len(f)))
    for r in np.flatnonzero(dense):
        m = np.flatnonzero(root == r)
        bits = np.unpackbits(f[m].view(np.uint8).reshape(len(m), -1), axis=1).mean(0) > 0.5
        middle = m[np.argmin(distances(f[m], np.packbits(bits).view(np.uint64)))]
        near = np.empty(len(m), int)
        for at in range(0, len(m), 256):
            d = distances(f[m[at:at + 256]][:, None], f[m][None])
            d[np.arange(len(d)), at + np.arange(len(d))] = 1 << 20
            near[at:at + 256] = d.argmin(1)
        for other in (np.full(len(m), middle), m[near]):
            left.append(np.minimum(m, other)[m != other])
            right.append(np.maximum(m, other)[m != other])
    return np.concatenate(left), np.concatenate(right), np.flatnonzero(dense[root])


def shard_edges(nodes: DataFrame, keys: list[np.ndarray], radius: int, width: int, pairs: bool, chunk: int = CHUNK) -> DataFrame:
    """nodes (id, f0..; ids unique) -> distinct edges (u, v) of linked ids.

    Without `pairs` the edges are a spanning forest of each shard. With them they are pairs to be verified, those of
    witnesses(), and a row (u, null) for each u of which a shard left out pairs.
    """
    entries = keyed(nodes, keys, width)
    names = ["id", *(f"f{w}" for w in range(width))]
    hot = written(entries.groupBy("key").count().filter(F.col("count") > chunk)
                  .select(F.col("key").alias("hot_key"), F.ceil(F.col("count") / chunk).cast("int").alias("chunks")), "hot-shards")
    n_hot = hot.count()
    if n_hot:
        chunk_of = F.pmod(F.xxhash64("id"), F.col("chunks")).cast("int")
        spread = F.when(F.col("chunks").isNull(), F.array(F.lit(0))).otherwise(F.transform(
            F.sequence(F.lit(0), F.col("chunks") - 1),
            lambda o: F.least(o, chunk_of) * F.col("chunks") + F.greatest(o, chunk_of)))
        entries = (entries.join(F.broadcast(hot) if n_hot <= BROADCAST_KEYS else hot, F.col("key") == F.col("hot_key"), "left")
                   .select("key", F.explode(spread).alias("part"), *names))
    else:
        entries = entries.select("key", F.lit(0).alias("part"), *names)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        no = np.empty(0, np.int64)

        def batch(us, vs, dense):
            both = np.unique(np.stack([np.concatenate([*us, no]), np.concatenate([*vs, no])], 1), axis=0)
            some = np.unique(np.concatenate(dense))
            v = pa.array(np.r_[both[:, 1], some], mask=np.arange(len(both) + len(some)) >= len(both))
            return pa.RecordBatch.from_arrays([pa.array(np.r_[both[:, 0], some]), v], ["u", "v"])

        def linked_edges(key, ids, f):
            """Spanning stars of whole shards, one after the other in sorted arrays."""
            new = np.r_[True, (key[1:] != key[:-1]).any(1)]
            starts = np.flatnonzero(new)
            shard = np.cumsum(new) - 1
            at = 0
            while at < len(key):  # whole shards, about TOGETHER rows
                k = np.searchsorted(starts, at + TOGETHER)
                end = int(starts[k]) if k < len(starts) else len(key)
                i, j = Trees(np.ascontiguousarray(f[at:end]), shard[at:end] - shard[at]).stars(radius)
                u, v = ids[at + i], ids[at + j]
                yield batch([np.maximum(u, v)], [np.minimum(u, v)], [ids[:0]])
                at = end

        def edges(key, ids, f):
            """Of whole shards, one after the other in sorted arrays."""
            starts = np.flatnonzero(np.r_[True, (key[1:] != key[:-1]).any(1)])
            sizes = np.diff(np.r_[starts, len(key)])
            us, vs, dense, held = [], [], [ids[:0]], 0

            def add(i, j):
                u, v = ids[i], ids[j]
                us.append(np.maximum(u, v)), vs.append(np.minimum(u, v))
                return len(u)

            little = np.repeat(sizes <= 8, sizes)
            for s in range(1, 8):  # small shards all together: each row with the s-th next of its shard
                i = np.flatnonzero(little[:-s] & (key[s:] == key[:-s]).all(1)) if len(key) > s else np.empty(0, int)
                i = i[distances(f[i], f[i + s]) <= radius]
                held += add(i, i + s)
            for at, n in zip(starts[sizes > 8].tolist(), sizes[sizes > 8].tolist()):
                i, j, some = witnesses(np.ascontiguousarray(f[at:at + n]), radius)
                held += add(at + i, at + j)
                dense.append(ids[at + some])
                if held > 1 << 20:
                    yield batch(us, vs, dense)
                    us[:], vs[:], dense[:], held = [], [], [ids[:0]], 0
            yield batch(us, vs, dense)

        rest, of_shards = None, edges if pairs else linked_edges
        for b in batches:
            if not len(b):
                continue
            key = np.stack([b.column(0).to_numpy(), b.column(1).to_numpy().astype(np.int64)], 1)
            ids = b.column(2).to_numpy()
            f = np.stack([b.column(3 + w).to_numpy() for w in range(width)], 1).view(np.uint64)
            now = key, ids, f
            if rest:
                now = tuple(np.concatenate(x) for x in zip(rest, now))
                key = now[0]
            last = len(key) - int(np.argmax((key[::-1] != key[-1]).any(1))) if (key != key[-1]).any() else 0
            if last:
                yield from of_shards(*(x[:last] for x in now))
            rest = tuple(x[last:] for x in now)
        if rest:
            yield from of_shards(*rest)

    return entries.repartition("key", "part").sortWithinPartitions("key", "part").mapInArrow(run, "u long, v long").distinct()


# ---------------------------------------------------------------- operators
def linked(docs: DataFrame, words: int = 4, radius: int = 4, per_tree: int = PER_TREE) -> DataFrame:
    """doc_id, fingerprint (16 hex digits), component_id (smallest doc_id reachable over links of at most `radius` bits)."""
    prints = written(fingerprints(docs, words).select("doc_id", "f0"), "fingerprints")
    nodes = written(prints.groupBy(F.col("f0").alias("id")).agg(F.min("doc_id").alias("first"), F.count("*").alias("n")), "distinct-fingerprints")
    n = nodes.count()
    found = shard_edges(nodes.select("id", F.col("id").alias("f0")), block_layout(64, radius, n, per_tree), radius, 1, pairs=False)
    named = _named(nodes, connected_components(found), n).withColumnRenamed("id", "k")
    return hot_join(prints, named, "f0", "k", "n", prints.count()).select(
        "doc_id", F.lower(F.lpad(F.hex("f0"), 16, "0")).alias("fingerprint"), F.col("head").alias("component_id"))


def _named(nodes: DataFrame, parts: DataFrame, n: int) -> DataFrame:
    """nodes (id, first, n) and the components of some of them -> id, n, head: the least `first` of the node's component."""
    placed = parts.select(F.col("node"), "component").join(nodes.select("id", "first"), F.col("node") == F.col("id")).drop("id")
    heads = placed.groupBy(F.col("component").alias("c")).agg(F.min("first").alias("head"), F.count("*").alias("members"))
    of_node = hot_join(placed, heads, "component", "c", "members", n).select("node", "head")
    return written(nodes.join(of_node, nodes["id"] == of_node["node"], "left").select("id", "n", F.coalesce("head", "first").alias("head")), "named-groups")


def expected_difference(similarity: float) -> float:
    """Share of fingerprint bits in which two equally long shingle sets of that Jaccard similarity are to differ."""
    return math.acos(min(1.0, 2 * similarity / (1 + similarity))) / math.pi


def shingle_sets(docs: DataFrame, nodes: DataFrame, ids: DataFrame, words: int) -> DataFrame:
    """(id, shingles) of the nodes in ids (id), written. docs has doc_id and text, nodes has id (the hash of the word
    sequence) and first (doc_id and mark of one of its rows)."""
    ends = ids.select(F.col("id").alias("end")).distinct()
    ends = written(nodes.join(ends, nodes["id"] == ends["end"], "left_semi").select(F.col("first.doc_id").alias("d"), F.col("first.mark").alias("m")).distinct(), "proposed-rows")
    side = F.broadcast(ends) if ends.count() <= BROADCAST_IDS else ends
    # shingle sets are made for these texts only; one row stands for a node
    some = docs.join(side, (docs["doc_id"] == F.col("d")) & (F.xxhash64(docs["text"]) == F.col("m")), "left_semi")
    sets = written(fingerprints(some, words, 64, shingles=True).select(F.col("seq").alias("id"), "shingles").dropDuplicates(["id"]), "shingle-sets")
    removed(docs.sparkSession, ends)
    return sets


def verified(sets: DataFrame, proposed: DataFrame, similarity: float) -> DataFrame:
    """The pairs (u, v) of node ids whose shingle sets have that Jaccard similarity, written."""
    left, right = sets.toDF("lu", "ls"), sets.toDF("rv", "rs")
    common = F.size(F.array_intersect("ls", "rs"))
    return written(proposed.join(left, F.col("u") == F.col("lu")).select("u", "v", "ls").join(right, F.col("v") == F.col("rv"))
                   .filter(common >= similarity * (F.size("ls") + F.size("rs") - common)).select("u", "v"), "links")


def prefix_pairs(sets: DataFrame, similarity: float, buckets: int = 1 << 20) -> DataFrame:
    """sets (id, shingles, component) -> distinct (u, v) of different components, among which are all pairs of that Jaccard
    similarity, written.

    Prefix filter: with shingles in one order for all (here: rarest first, by hashed counts), two sets that overlap so much
    share a shingle among the first 1 - similarity of the larger set and the first 1 - 2 similarity / (1 + similarity) of
    the smaller one. Texts that share a template but less than that meet nowhere: the template's shingles, being frequent,
    stand behind their own. Shingles that only one component has are left out before the join; sizes and places bound the
    overlap of the others.
    """
    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = np.zeros(buckets, np.int64)
        for b in small(batches):
            total += np.bincount(b.column(0).flatten().to_numpy().view(np.uint32) % buckets, minlength=buckets)
        at = np.flatnonzero(total)
        yield pa.RecordBatch.from_arrays([pa.array(at.astype(np.int32)), pa.array(total[at])], ["bucket", "n"])

    got = sets.select("shingles").mapInArrow(count, "bucket int, n long").groupBy("bucket").agg(F.sum("n").alias("n")).toArrow()
    often = np.zeros(buckets, np.int64)
    often[got["bucket"].to_numpy()] = got["n"].to_numpy()
    shared = sets.sparkSession.sparkContext.broadcast(often)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in small(batches):
            shingle, which, size, place, indexed = [], [], [], [], []
            for k, x in enumerate(b.column(1).to_pylist()):
                x = np.array(x, np.int32)
                n = len(x)
                if not n:
                    continue
                probe = n - math.ceil(similarity * n - 1e-9) + 1
                index = n - math.ceil(2 * similarity / (1 + similarity) * n - 1e-9) + 1
                first = x[np.lexsort((x, shared.value[x.view(np.uint32) % buckets]))][:probe]
                shingle.append(first), which.append(np.full(len(first), k)), size.append(np.full(len(first), n))
                place.append(np.arange(len(first))), indexed.append(np.arange(len(first)) < index)
            if shingle:
                k = pa.array(np.concatenate(which))
                yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(shingle)), b.column(0).take(k), b.column(2).take(k), pa.array(np.concatenate(size).astype(np.int32)),
                                                  pa.array(np.concatenate(place).astype(np.int32)), pa.array(np.concatenate(indexed))], ["shingle", "id", "component", "size", "place", "indexed"])

    rows = written(sets.select("id", "shingles", "component").mapInArrow(run, "shingle int, id long, component long, size int, place int, indexed boolean"), "prefixes")
    met = rows.groupBy("shingle").agg(F.min("component").alias("a"), F.max("component").alias("b")).filter("a <> b").select(F.col("shingle").alias("met"))
    rows = rows.join(met, F.col("shingle") == F.col("met"), "left_semi")
    larger = rows.select(*(F.col(c).alias(f"a_{c}") for c in rows.columns))
    smaller = rows.filter("indexed").select(*(F.col(c).alias(f"b_{c}") for c in rows.columns))
    overlap = F.least(F.col("a_size") - F.col("a_place"), F.col("b_size") - F.col("b_place"))
    able = ((F.col("a_component") != F.col("b_component")) & (F.struct("b_size", "b_id") < F.struct("a_size", "a_id"))
            & (F.col("b_size") >= similarity * F.col("a_size") - 1e-6) & (overlap >= similarity / (1 + similarity) * (F.col("a_size") + F.col("b_size")) - 1e-6))
    return written(larger.join(smaller, (F.col("a_shingle") == F.col("b_shingle")) & able).select(
        F.greatest("a_id", "b_id").alias("u"), F.least("a_id", "b_id").alias("v")).distinct(), "undecided")


def near_duplicates(docs: DataFrame, words: int = 5, similarity: float = 0.8, bits: int = 192, recall: float = 0.999) -> DataFrame:
    """docs (doc_id, text) -> doc_id, mark (xxhash64 of the text), component_id, stays: groups of texts linked by a Jaccard
    similarity of their word shingles of `similarity` or more, exact copies included. component_id is the group's smallest
    doc_id; `stays` marks the rows of one text of the group, that with this doc_id (several: the smallest mark).

    Wide SimHash fingerprints of the distinct shingles propose pairs (within 3.5 standard deviations of the expected number
    of differing bits; shard tables reach `recall` for pairs that differ in one deviation more bits than expected at
    `similarity`); the shingle sets of each proposed pair decide. Every pair that meets in a shard within that distance is
    decided: by its sets, or because links verified before join its ends. Texts of the same words are one node, named by
    the hash of their words, so several texts of one doc_id stay apart.
    """
    width, differs = bits // 64, expected_difference(similarity)
    deviation = math.sqrt(differs * (1 - differs) / bits)
    radius = math.ceil(bits * (differs + 3.5 * deviation))
    docs = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text")
    prints = written(fingerprints(docs, words, bits, distinct=True), "fingerprints")
    f = [f"f{w}" for w in range(width)]
    row = F.when(F.col("doc_id").isNotNull(), F.struct("doc_id", "mark"))
    nodes = written(prints.groupBy(F.col("seq").alias("id")).agg(*(F.min(x).alias(x) for x in f), F.min(row).alias("first"), F.count("*").alias("n"))
                    .filter("first is not null"), "distinct-texts")
    n = nodes.count()
    keys = sampled_keys(bits, n, differs + deviation, recall)
    proposed = written(shard_edges(nodes.select("id", *f), keys, radius, width, pairs=True), "proposed")
    ends = proposed.filter("v is not null").select(F.explode(F.array("u", "v")).alias("id"))
    sets = shingle_sets(docs, nodes, ends, words)
    links = verified(sets, proposed.filter("v is not null"), similarity)
    parts = connected_components(links)
    dense = written(proposed.filter("v is null").select(F.col("u").alias("dense_id")), "dense-ids")
    tables = [prints, nodes, proposed, links, dense, sets]
    if (many := dense.count()):
        # each row of a dense group has a proposed pair, so its set is there
        some = sets.join(F.broadcast(dense) if many <= BROADCAST_IDS else dense, sets["id"] == F.col("dense_id"), "left_semi")
        some = written(some.join(parts, some["id"] == parts["node"], "left").select("id", "shingles", F.coalesce("component", "id").alias("component")), "dense-texts")
        undecided = prefix_pairs(some, similarity)
        more = verified(sets, undecided, similarity)
        parts = connected_components(links.unionAll(more))
        tables += [some, undecided, more]
    named = _named(nodes.select("id", "first", "n"), parts, n)
    out = hot_join(prints.select("doc_id", "mark", "seq"), named, "seq", "id", "n", prints.count(), "left")
    own = F.col("doc_id").isNull() | (F.struct("doc_id", "mark") == F.col("head"))
    out = written(out.select("doc_id", "mark", F.col("head.doc_id").alias("component_id"), own.alias("stays")), "near-duplicates")
    for table in tables:
        removed(docs.sparkSession, table)
    return out


def one_of_each(docs: DataFrame, groups: DataFrame, broadcast_rows: int = BROADCAST_IDS) -> DataFrame:
    """The rows of docs that name their group, given near_duplicates(docs).

    A row is known by its doc_id and its text, so other texts of the same doc_id are not touched. Of rows that repeat id
    and text one stays; a row without an id cannot be named and stays. The rows that go are broadcast (16 bytes each) up to
    a checked number, so texts are only shuffled beyond it.
    """
    p = free_prefix(docs, ["doc", "mark"])
    doc, mark = F.col(f"{p}doc"), F.col(f"{p}mark")
    same = docs["doc_id"].cast("long").eqNullSafe(doc) & F.xxhash64(docs["text"]).eqNullSafe(mark)
    listed = lambda rows, label: written(rows.select(F.col("doc_id").alias(f"{p}doc"), F.col("mark").alias(f"{p}mark")).distinct(), label)
    side = lambda rows: F.broadcast(rows) if rows.count() <= broadcast_rows else rows
    gone = listed(groups.filter("not stays"), "copies")
    again = listed(groups.filter("stays and doc_id is not null").groupBy("doc_id", "mark").count().filter("count > 1"), "repeated-rows")
    kept = docs.join(side(gone), same, "left_anti")
    if again.isEmpty():
        return kept
    once = side(again)
    return kept.join(once, same, "left_anti").unionByName(kept.join(once, same, "left_semi").dropDuplicates(["doc_id", "text"]))
