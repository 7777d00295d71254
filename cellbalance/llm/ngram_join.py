"""Prefix-tree join of n-gram sets: all pairs with Jaccard similarity of 0.8 or more, as connected components.

1. Texts become sets of hashed five-word shingles; equal sets are one class, whatever the number of copies.
2. Global order of shingles: rare ones by hash, then those that are frequent inside some slice, by frequency. The list of
   frequent ones is bounded (``MAX_FREQUENT``); the order is a matter of speed, any order gives the same links.
3. With the first ``n - ceil(0.8 n) + l`` shingles of each set as its prefix, l = 1 + n div 20, two similar sets share at
   least l prefix shingles (the smaller l of the two). Classes that share none with another class are done. In the others,
   the first class of each shared shingle is a centre, and each class goes to the centre it meets most often.
4. Each centre's block holds the ordered sets of its star as a prefix tree: shared beginnings are one path, a traversal
   with the centre's set keeps one partial overlap per path, and a subtree is left when the overlap plus the remaining
   lengths can't reach the bound of its smallest set.
5. The classes of one centre are a family. Families whose links give more than one component are dealt into chunks by hash,
   every two chunks meet in a tile, and one chunk's tree is traversed with the other's sets, leaving subtrees that are in
   the query's component already. A tile tells no more links than it has sets, so no pairs of a group are listed.
6. What is left are links between families. A class that shares enough prefix shingles with all of a larger family together
   is a query to that family's trees. The components of all links are final; pairs inside a component can't change it.

Null and empty texts have no shingles and are linked with nothing. Rows that share a doc_id are one node. Extra columns are
ignored. An empty table gives no rows.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import batches_of, components, documents, join_hot, mix, table, window_hashes, word_hashes, words_of

SHINGLE = 5
#: Similarity as a fraction, NUM / DEN.
NUM, DEN = 4, 5
#: Most shingles that are ordered by frequency, and how often one must occur in a slice of texts.
MAX_FREQUENT = 1 << 17
FREQUENT_IN_SLICE = 2
SLICE_BYTES = 8 << 20
#: A star is tried only with a centre that shares this part of the prefix; it is a matter of speed, step 5 finds the rest.
STAR_SHARE = 0.25
#: Rounds in which classes and shingles that can't give a pair across families are left out, before families meet.
CORE_ROUNDS = 2
#: Sets and shingles in a chunk of a family, on average.
CHUNK_SETS, CHUNK_SHINGLES = 256, 1 << 18


def shingles(text: str | None, k: int = SHINGLE) -> np.ndarray:
    """Distinct shingle hashes, ascending; a text of fewer words is one shingle."""
    h = word_hashes(words_of(text, lower=True))
    return np.unique(window_hashes(h, min(k, len(h)))) if len(h) else h


def signature(s: np.ndarray) -> int:
    """Hash of a whole set."""
    with np.errstate(over="ignore"):
        m = mix(s * np.uint64(0xA24BAED4963EE407))
        return int(mix(np.array([m.sum() + np.bitwise_xor.reduce(m) * np.uint64(0x9FB21C651E98DF25) + np.uint64(len(s))], np.uint64)).view(np.int64)[0])


class Order:
    """The global order of shingles."""

    def __init__(self, frequent: list[tuple[int, int]]):
        """(shingle as a signed long, count)"""
        ranked = sorted(frequent, key=lambda x: (x[1], x[0]))
        hashes = np.array([h for h, _ in ranked], np.int64).view(np.uint64)
        by = np.argsort(hashes)
        self.hash, self.rank = hashes[by], by.astype(np.int64)

    def ordered(self, s: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """The set in order, and sort keys: places in the order for comparisons (rare: 0 and the hash; frequent: 1 + rank)."""
        if not len(self.hash) or not len(s):
            return s, np.zeros(len(s), np.int64)
        rank = self.rank_of(s)
        by = np.argsort(rank, kind="stable")
        return s[by], rank[by]

    def rank_of(self, s: np.ndarray) -> np.ndarray:
        if not len(self.hash):
            return np.zeros(len(s), np.int64)
        at = np.minimum(np.searchsorted(self.hash, s), len(self.hash) - 1)
        return np.where(self.hash[at] == s, self.rank[at] + 1, 0)


def least_shared(n):
    """Prefix shingles that a similar set of this size or more must share."""
    return 1 + n // 20


def prefix_length(n: int) -> int:
    return min(n, n - -(-NUM * n // DEN) + least_shared(n))


def needed(a: int, b: int) -> int:
    """Least overlap of two sets of these sizes that are similar."""
    return -(-NUM * (a + b) // (NUM + DEN))


# ---------------------------------------------------------------- the tree
class PrefixTree:
    """Ordered sets in a path-compressed trie. Sets are given in lexicographic order of their places."""

    __slots__ = ("run", "children", "ends", "least", "most", "depth", "group")

    def __init__(self, places: list[np.ndarray], names: list, depth: int = 0, groups: dict | None = None):
        """``places``: sets as ascending arrays of place numbers. ``groups``: each name's group; without it, nothing is skipped."""
        first, last = places[0], places[-1]
        m = min(len(first), len(last)) - depth
        unlike = np.flatnonzero(first[depth : depth + m] != last[depth : depth + m])
        end = depth + (int(unlike[0]) if len(unlike) else m)
        self.run, self.depth = first[depth:end], end
        self.least, self.most = min(map(len, places)), max(map(len, places))
        within = {groups[n] for n in names} if groups else ()
        self.group = within.pop() if len(within) == 1 else None
        self.ends = [n for p, n in zip(places, names) if len(p) == end]
        self.children = []
        rest = [(p, n) for p, n in zip(places, names) if len(p) > end]
        start = 0
        for i in range(1, len(rest) + 1):
            if i == len(rest) or rest[i][0][end] != rest[start][0][end]:
                self.children.append(PrefixTree([p for p, _ in rest[start:i]], [n for _, n in rest[start:i]], end, groups))
                start = i

    def similar(self, query: np.ndarray, skip=lambda group: False) -> list:
        """Names of the sets similar to the query, an ascending array of place numbers; subtrees of one group may be skipped."""
        found, stack, q = [], [(self, 0)], len(query)
        while stack:
            node, overlap = stack.pop()
            if node.group is not None and skip(node.group):
                continue
            used = 0
            if len(node.run):
                at = np.searchsorted(query, node.run)
                overlap += int((query[np.minimum(at, q - 1)] == node.run).sum())
                used = int(np.searchsorted(query, node.run[-1], "right"))
            if node.ends and overlap >= needed(q, node.depth):
                found += node.ends
            for child in node.children:
                # the query's shingles up to this path's last one are spent
                if overlap + min(child.most - node.depth, q - used) >= needed(q, child.least):
                    stack.append((child, overlap))
        return found


def placed(sets: list[np.ndarray], rank) -> list[np.ndarray]:
    """The sets as ascending place numbers in their common order. ``rank`` gives the order's ranks of hashes."""
    every = np.unique(np.concatenate(sets))
    place = np.empty(len(every), np.int64)
    place[np.lexsort((every, rank(every)))] = np.arange(len(every))
    return [np.sort(place[np.searchsorted(every, s)]) for s in sets]


def tree_of(sets: list[tuple[int, np.ndarray]], groups: dict | None = None) -> PrefixTree:
    """Tree of (name, places)."""
    by = sorted(sets, key=lambda x: x[1].astype(">i8").tobytes())
    return PrefixTree([p for _, p in by], [n for n, _ in by], 0, groups)


def block_links(centre: np.ndarray, members: list[tuple[int, np.ndarray]], rank) -> list[int]:
    """Members similar to the centre."""
    query, *places = placed([centre, *(s for _, s in members)], rank)
    return tree_of([(n, p) for (n, _), p in zip(members, places)]).similar(query)


def tile_links(members: list[tuple[int, int, int, np.ndarray]], rank) -> list[tuple[int, int]]:
    """Links between two chunks, or within one, that join components. ``members``: (name, component, chunk, set)."""
    parent: dict[int, int] = {}

    def root(x: int) -> int:
        while (up := parent.get(x, x)) != x:
            parent[x] = x = parent.get(up, up)
        return x

    places = placed([s for *_, s in members], rank)
    component = {n: c for n, c, _, _ in members}
    low = min(c for _, _, c, _ in members)
    alone = all(c == low for _, _, c, _ in members)
    tree = tree_of([(n, p) for (n, _, c, _), p in zip(members, places) if c == low], component)
    out = []
    for (name, own, chunk, _), p in zip(members, places):
        if chunk == low and not alone:
            continue
        for other in tree.similar(p, lambda group: root(group) == root(own)):
            a, b = root(own), root(component[other])
            if a != b:
                parent[a] = b
                out.append((min(name, other), max(name, other)))
    return out


# ---------------------------------------------------------------- Spark
def _sets(docs: DataFrame) -> DataFrame:
    """(doc_id, n, sig) of documents; rows with a null sig report a shingle (doc_id) found n times in a slice."""

    def run(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches_of(it, SLICE_BYTES):
            sets = [shingles(t) for t in b.column("text").to_pylist()]
            n = [len(s) for s in sets]
            sig = [signature(s) if len(s) else 0 for s in sets]
            distinct = list({k: s for k, s in zip(sig, sets) if len(s)}.values())
            h, c = np.unique(np.concatenate(distinct), return_counts=True) if distinct else (np.zeros(0, np.uint64), np.zeros(0, np.int64))
            often = c >= FREQUENT_IN_SLICE
            yield pa.RecordBatch.from_arrays([pa.concat_arrays([b.column("doc_id"), pa.array(h[often].view(np.int64))]), pa.array(np.concatenate([np.array(n, np.int64), c[often]])), pa.array(sig + [None] * int(often.sum()), pa.int64())], names=["doc_id", "n", "sig"])

    return docs.mapInArrow(run, "doc_id long, n long, sig long")


def _prefixes(docs: DataFrame, order) -> DataFrame:
    """(token, sig, n): the first shingles of each set; copies inside a slice once."""

    def run(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        rank = order.value
        for b in batches_of(it, 4 << 20):
            seen, parts = set(), []
            for text in b.column("text").to_pylist():
                s = shingles(text)
                sig = signature(s) if len(s) else 0
                if not len(s) or sig in seen:
                    continue
                seen.add(sig)
                p = prefix_length(len(s))
                parts.append((rank.ordered(s)[0][:p].view(np.int64), np.full(p, sig, np.int64), np.full(p, len(s), np.int32)))
            if parts:
                yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(c)) for c in zip(*parts)], names=["token", "sig", "n"])

    return docs.select("text").mapInArrow(run, "token long, sig long, n int")


def _shared(prefixes: DataFrame) -> DataFrame:
    """Prefix rows whose shingle is in two classes or more, with the first of these as centre and the row's place among them.

    Rows come sorted, so a group of any size passes through with one row held back.
    """
    names = ["token", "sig", "n"]

    def run(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, centre, sent, at = None, None, False, 0  # last distinct row; first sig of its shingle; whether the row went out; its place
        for b in it:
            cols = [np.asarray(b.column(c)) for c in names]
            if not len(cols[0]):
                continue
            if held is not None:
                cols = [np.concatenate([[h], c]) for h, c in zip(held, cols)]
            token, sig = cols[0], cols[1]
            new = np.ones(len(token), bool)
            new[1:] = (token[1:] != token[:-1]) | (sig[1:] != sig[:-1])
            cols = [c[new] for c in cols]
            token, sig = cols[0], cols[1]
            first = np.ones(len(token), bool)
            first[1:] = token[1:] != token[:-1]
            group = np.cumsum(first) - 1
            centres = sig[first]
            if held is not None:
                centres = np.concatenate([[centre], centres[1:]])
            size = np.bincount(group)
            place = np.arange(len(token)) - np.flatnonzero(first)[group]
            if held is not None:
                place[group == 0] += at
            out = size[group] > 1
            if held is not None:
                if sent:
                    out[group == 0] = True
                    out[0] = False
            tail_sent = bool(out[-1]) or (sent and len(token) == 1 and held is not None)
            held, centre, sent, at = [c[-1] for c in cols], centres[-1], tail_sent, int(place[-1])
            if out.any():
                yield pa.RecordBatch.from_arrays([pa.array(cols[0][out].astype(np.int64)), pa.array(cols[1][out].astype(np.int64)), pa.array(cols[2][out].astype(np.int32)), pa.array(centres[group][out].astype(np.int64)), pa.array(place[out].astype(np.int32))], names=[*names, "centre", "place"])

    return prefixes.repartition("token").sortWithinPartitions("token", "sig").mapInArrow(run, "token long, sig long, n int, centre long, place int")


def _blocks(memberships: DataFrame, docs: DataFrame, classes: DataFrame) -> DataFrame:
    """(block, node, component, chunk, data) of ``memberships`` (node, block, component, chunk): each class's set in all its blocks."""
    wanted = memberships.join(classes.select(F.col("sig").alias("node"), F.col("least").alias("doc_id")), "node").groupBy("doc_id", "node").agg(F.collect_list(F.struct("block", "component", "chunk")).alias("places"))

    def spread(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        types = (pa.int64(), pa.int64(), pa.int64(), pa.int32(), pa.binary())
        for b in batches_of(it):
            rows, size = [], 0
            for node, text, places in zip(b.column("node").to_pylist(), b.column("text").to_pylist(), b.column("places").to_pylist()):
                s = shingles(text)
                if len(s) and signature(s) == node:  # another row may have the same id
                    data = s.tobytes()
                    for p in places:
                        rows.append((p["block"], node, p["component"], p["chunk"], data))
                        size += len(data)
                        if size > SLICE_BYTES:
                            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows), types)], names=["block", "node", "component", "chunk", "data"])
                            rows, size = [], 0
            if rows:
                yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows), types)], names=["block", "node", "component", "chunk", "data"])

    return docs.join(wanted, "doc_id").select("node", "text", "places").mapInArrow(spread, "block long, node long, component long, chunk int, data binary")


def _rows(it: Iterator[pa.RecordBatch]) -> Iterator[tuple]:
    for b in it:
        for lo in range(0, b.num_rows, 500):
            part = b.slice(lo, 500)
            yield from zip(*(part.column(c).to_pylist() for c in ("block", "node", "component", "chunk", "data")))


def _verified(pairs: DataFrame, docs: DataFrame, classes: DataFrame, order) -> DataFrame:
    """The pairs (centre, sig) that are links, by one prefix tree per centre."""
    memberships = pairs.select(F.col("sig").alias("node"), F.col("centre").alias("block")).unionByName(pairs.select(F.col("centre").alias("node"), F.col("centre").alias("block")).distinct())

    def join(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        rank = order.value.rank_of
        now, own, members, seen = None, None, [], set()

        def close() -> Iterator[pa.RecordBatch]:
            if own is not None and members:
                found = sorted(set(block_links(own, members, rank)))
                if found:
                    yield pa.RecordBatch.from_arrays([pa.array([now] * len(found), pa.int64()), pa.array(found, pa.int64())], names=["a", "b"])

        for centre, node, _, _, data in _rows(it):
            if centre != now:
                yield from close()
                now, own, members, seen = centre, None, [], set()
            if node in seen:
                continue
            seen.add(node)
            s = np.frombuffer(data, np.uint64)
            if node == centre:
                own = s
            else:
                members.append((node, s))
            if len(members) >= 500 and own is not None:  # a large star is joined in parts
                yield from close()
                members = []
        yield from close()

    blocks = _blocks(memberships.withColumn("component", F.lit(0).cast("long")).withColumn("chunk", F.lit(0)), docs, classes)
    # the centre's own set comes first in its block
    return blocks.repartition("block").sortWithinPartitions("block", F.col("node") != F.col("block")).mapInArrow(join, "a long, b long")


def _tiled(memberships: DataFrame, docs: DataFrame, classes: DataFrame, order) -> DataFrame:
    """Links (a, b) that join components inside each block; sets of its lowest chunk are the tree, the others are queries."""

    def join(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        rank = order.value.rank_of
        now, members, seen = None, [], set()

        def close() -> Iterator[pa.RecordBatch]:
            found = tile_links(members, rank) if len(members) > 1 else []
            if found:
                yield pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in zip(*found)], names=["a", "b"])

        for block, node, component, chunk, data in _rows(it):
            if block != now:
                yield from close()
                now, members, seen = block, [], set()
            if node not in seen:
                seen.add(node)
                members.append((node, component, chunk, np.frombuffer(data, np.uint64)))
        yield from close()

    return _blocks(memberships, docs, classes).repartition("block").sortWithinPartitions("block").mapInArrow(join, "a long, b long")


def _within(nodes: DataFrame, docs: DataFrame, classes: DataFrame, order) -> DataFrame:
    """Links (a, b) that join components inside families. ``nodes``: (node, n, family, component)."""
    size = nodes.groupBy("family").agg(F.count("*").alias("m"), F.sum("n").alias("total"), F.min("component").alias("x"), F.max("component").alias("y")).filter("x < y")
    chunks = size.select("family", F.greatest(F.ceil(F.col("m") / CHUNK_SETS), F.ceil(F.col("total") / CHUNK_SHINGLES)).cast("int").alias("chunks"), "m")
    own = join_hot(nodes, table(chunks, "family-chunks"), "family", "m").withColumn("chunk", F.pmod(F.xxhash64("node"), F.col("chunks")).cast("int"))
    tiles = own.select("node", "family", "component", "chunk", F.explode(F.sequence(F.lit(0), F.col("chunks") - 1)).alias("other"))
    memberships = tiles.select("node", F.xxhash64("family", F.least("chunk", "other"), F.greatest("chunk", "other")).alias("block"), "component", "chunk")

    return _tiled(memberships, docs, classes, order)


def _across(shared: DataFrame, nodes: DataFrame) -> DataFrame:
    """Memberships in blocks of a family and the classes of smaller families that share enough prefix shingles with it."""
    rows = shared.select("token", "sig", "n").join(nodes.select(F.col("node").alias("sig"), "family", "component"), "sig", "left")
    rows = table(rows.withColumn("component", F.coalesce("component", "sig")).withColumn("family", F.coalesce("family", "sig")), "labelled-prefixes")
    fewest = 1 + F.floor(F.ceil(F.col("n") * NUM / DEN) / 20)
    for r in range(CORE_ROUNDS):
        mixed = rows.groupBy("token").agg(F.min("component").alias("x"), F.max("component").alias("y"), F.min("family").alias("u"), F.max("family").alias("v")).filter("x < y and u < v").select("token")
        met = rows.join(mixed, "token", "left_semi")
        # a class with fewer such shingles than its smallest partner asks for has no partner
        enough = met.groupBy("sig").agg(F.count("*").alias("c"), F.max("n").alias("n")).filter(F.col("c") >= fewest).select("sig")
        rows = table(met.join(enough, "sig", "left_semi"), f"core-{r}")
    # a class of the smaller family shares no more with any class of the larger one than with all of that family together
    size = rows.select("sig", "family").distinct().groupBy("family").agg(F.count("*").alias("m"))
    sized = table(rows.join(size, "family"), "sized-families")
    other = sized.select("token", F.col("family").alias("with"), F.struct("m", "family").alias("above")).distinct()
    meets = sized.join(other, "token").filter(F.struct("m", "family") < F.col("above")).groupBy("sig", "with").agg(F.count("*").alias("c"), F.max("n").alias("n"))
    meets = table(meets.filter(F.col("c") >= fewest).select("sig", "with"), "met-families")
    nodes = rows.select("sig", "n", "family", "component").distinct()
    visitors = meets.groupBy("with").agg(F.ceil(F.count("*") / CHUNK_SETS).cast("int").alias("groups"))
    chunks = nodes.groupBy(F.col("family").alias("with")).agg(F.greatest(F.ceil(F.count("*") / CHUNK_SETS), F.ceil(F.sum("n") / CHUNK_SHINGLES)).cast("int").alias("chunks"))
    plan = table(visitors.join(chunks, "with"), "visited-families")
    part = lambda key, parts: F.pmod(F.xxhash64(key), F.col(parts)).cast("int")
    every = lambda parts: F.explode(F.sequence(F.lit(0), F.col(parts) - 1))
    hosts = nodes.withColumnRenamed("family", "with").join(plan, "with").select("sig", "component", "with", part("sig", "chunks").alias("i"), every("groups").alias("j"), F.lit(0).alias("chunk"))
    guests = meets.join(plan, "with").join(nodes.select("sig", "component"), "sig").select("sig", "component", "with", every("chunks").alias("i"), part("sig", "groups").alias("j"), F.lit(1).alias("chunk"))
    return hosts.unionByName(guests).select(F.col("sig").alias("node"), F.xxhash64("with", "i", "j").alias("block"), "component", "chunk")


def jaccard_components(docs: DataFrame) -> DataFrame:
    """(doc_id, n_shingles, component_id) of every document."""
    docs = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    found = table(_sets(docs), "shingle-sets")
    frequent = found.filter("sig is null").groupBy("doc_id").agg(F.sum("n").alias("c")).orderBy(F.desc("c"), "doc_id").limit(MAX_FREQUENT)
    order = docs.sparkSession.sparkContext.broadcast(Order([(r[0], r[1]) for r in frequent.collect()]))  # at most MAX_FREQUENT
    sets = found.filter("sig is not null")
    classes = table(sets.filter("n > 0").groupBy("sig").agg(F.min("doc_id").alias("least"), F.count("*").alias("copies")), "set-classes")
    shared = table(_shared(_prefixes(docs, order)), "shared-prefixes")
    met = shared.filter("place > 0").groupBy("sig", "centre").agg(F.count("*").alias("c"), F.max("n").alias("n")).filter(F.col("c") >= STAR_SHARE * (1 - NUM / DEN) * F.col("n"))
    stars = table(met.groupBy("sig").agg(F.max(F.struct("c", "centre")).alias("x"), F.max("n").alias("n")).select("sig", "n", "x.centre"), "stars")
    links = table(_verified(stars.select("sig", "centre"), docs, classes, order), "star-links")
    # a class without a centre is its own family's first
    node = lambda of: of.join(components(links).withColumnRenamed("id", "node"), "node", "left").withColumn("component", F.coalesce("component", "node"))
    families = stars.select(F.col("sig").alias("node"), F.col("n").cast("long").alias("n"), F.col("centre").alias("family"))
    links = table(links.unionByName(_within(table(node(families), "families"), docs, classes, order)), "family-links")
    own = stars.select(F.explode(F.array("sig", "centre")).alias("node")).unionByName(links.select(F.explode(F.array("a", "b")).alias("node"))).distinct()
    label = components(links)
    nodes = table(own.join(families.select("node", "family"), "node", "left").join(label.withColumnRenamed("id", "node"), "node", "left").select("node", F.coalesce("family", "node").alias("family"), F.coalesce("component", "node").alias("component")), "labelled-families")
    extra = table(_tiled(_across(shared, nodes), docs, classes, order), "cross-links")
    if not extra.isEmpty():
        label = components(links.unionByName(extra))
    # rows that share a doc_id are one node: their classes are linked
    several = sets.filter("n > 0").groupBy("doc_id").agg(F.min("sig").alias("x"), F.max("sig").alias("y")).filter("x <> y").select("doc_id", "x")
    same = table(sets.filter("n > 0").join(several, "doc_id").filter("sig <> x").select(F.col("sig").alias("a"), F.col("x").alias("b")).distinct(), "same-ids")
    if not same.isEmpty():
        label = components(links.unionByName(extra).unionByName(same))
    # the smallest document of a component's classes
    labelled = table(classes.join(label.select(F.col("id").alias("sig"), "component"), "sig", "left").withColumn("component", F.coalesce("component", "sig")), "labelled-classes")
    smallest = labelled.groupBy("component").agg(F.min("least").alias("component_id"))
    of_class = table(labelled.join(smallest, "component").select("sig", "copies", "component_id"), "class-components")
    full = join_hot(sets.filter("n > 0"), of_class, "sig", "copies").select("doc_id", F.col("n").alias("n_shingles"), "component_id")
    return full.unionByName(sets.filter("n = 0").select("doc_id", F.col("n").alias("n_shingles"), F.col("doc_id").alias("component_id")))


def keep_one(docs: DataFrame) -> DataFrame:
    """One document of each component, the one with the smallest id, with all columns; of rows with one id the one with the first text,
    and of those the one whose other columns come first as JSON. Rows with a null id stay."""
    ids = F.col("doc_id").cast("long")
    kept = jaccard_components(docs.filter(ids.isNotNull())).filter("doc_id = component_id").select(F.col("doc_id").alias("kept document")).distinct()
    one = docs.join(kept, ids == F.col("kept document"), "left_semi")
    first = Window.partitionBy(ids).orderBy("text", F.to_json(F.struct(*docs.columns)))
    return one.withColumn("place among rows", F.row_number().over(first)).filter(F.col("place among rows") == 1).select(*docs.columns).unionByName(docs.filter(ids.isNull()))


def op6_prefix_tree_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    return jaccard_components(documents(spark, sf_dir))
