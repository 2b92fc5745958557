"""Exact similarity join of shingle sets with adaptive multi-match prefixes.

Equal sets collapse first. Shingles get a global order, rare ones first, from a count sketch of fixed
size over all documents. Every document lengthens its prefix of n - ceil(t n) + 1 shingles to l - 1 more,
with l chosen by the cost that the sketch expects, and goes on only if it shares as many prefix shingles
as it or a holder of one of them asks for. Two sets that reach the threshold then have a key in common (two
neighbouring prefix shingles, see set_keys), so all links lie inside the components of the graph that ties
the holders of each key. Documents are dealt out by their least shingle before keys are made, so most near
copies meet in one task and send each key once; every task contracts what it ties, and no pairs are listed.

The sets of one component are brought together. Components of more than one block first get hubs: each set
is compared with its component's hub, which ties large groups of near copies in linear time, and pairs of
blocks of one class that is tied already are left out. Each other pair of blocks is solved in memory: every
document lengthens its prefix to l more shingles where the estimated cost of candidates falls, and a pair
is verified only if the prefixes share min(l, l') of them. Pairs that are connected already are not
verified again, which loses no component.
"""

from __future__ import annotations

from functools import lru_cache

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from zplane.components import components, union_find
from zplane.llm import shingles as sh
from zplane.session import discard, release, ship, stored

#: Width of the count sketch (counts of 4 bytes), shingles that a block of a component holds, documents of one
#: least shingle (or one hub) that a task takes, rounds of hubs, and turns in which prefixes are compared.
SKETCH_BITS, BLOCK_SHINGLES, CROWD, HUB_ROUNDS, TURNS = 22, 150_000, 4000, 2, 4
_PARTS = 16


def needed(n: int, percent: int) -> int:
    """The least overlap with any set that a set of n must have: ceil(percent * n / 100)."""
    return -(-percent * n // 100)


def _sketch(docs: DataFrame, k: int) -> np.ndarray:
    """Counts of all documents' shingles in 2^SKETCH_BITS cells, summed per task and then per part."""
    cells = 1 << SKETCH_BITS
    size = cells // _PARTS

    def run(batches):
        import zlib

        import pyarrow as pa

        from zplane.llm.jaccard_join import _batched_sets
        from zplane.session import trim, worker_cache

        worker_cache(None)
        total = np.zeros(cells, np.int32)
        for _, sets in _batched_sets(batches, k, 0):
            if sets:
                at, n = np.unique((np.concatenate(sets) >> np.uint64(64 - SKETCH_BITS)).astype(np.int64), return_counts=True)
                total[at] += n.astype(np.int32)
        blobs = [zlib.compress(total[i * size : (i + 1) * size].tobytes(), 1) for i in range(_PARTS)]
        yield pa.RecordBatch.from_arrays([pa.array(range(_PARTS), pa.int32()), pa.array(blobs, pa.binary())], ["part", "counts"])
        del total, blobs
        trim()

    def add(batches):
        import zlib

        import pyarrow as pa

        sums: dict[int, np.ndarray] = {}
        for b in batches:
            for part, blob in zip(b.column(0).to_pylist(), b.column(1).to_pylist()):
                x = np.frombuffer(zlib.decompress(blob), np.int32)
                sums[part] = sums[part] + x if part in sums else x.astype(np.int64)
        for part, x in sums.items():
            blob = zlib.compress(np.minimum(x, 2**31 - 1).astype(np.int32).tobytes(), 1)
            yield pa.RecordBatch.from_arrays([pa.array([part], pa.int32()), pa.array([blob], pa.binary())], ["part", "counts"])

    kind = "part int, counts binary"
    rows = docs.select("text").mapInArrow(run, kind).repartition(_PARTS, "part").mapInArrow(add, kind).collect()  # of fixed size
    import zlib

    out = np.zeros(cells, np.int32)
    for r in rows:  # one of each part
        out[r["part"] * size : (r["part"] + 1) * size] = np.frombuffer(zlib.decompress(r["counts"]), np.int32)
    return out


def _levels(counts: np.ndarray) -> np.ndarray:
    """How far each cell's count stands out of the mean load, in doublings (0: not); orders shingles rare first.

    The driver does this, so doubles are made for a part of the cells at a time.
    """
    mean = max(1.0, float(counts.mean()))
    out = np.empty(len(counts), np.uint8)
    size = -(-len(counts) // _PARTS)
    for lo in range(0, len(counts), size):
        over = np.maximum(0, counts[lo : lo + size] - mean - 4 * np.sqrt(mean) - 4)
        out[lo : lo + size] = np.ceil(np.log2(over + 1))
    return out


def _profiles(docs: DataFrame, k: int, percent: int, levels: np.ndarray) -> DataFrame:
    """(doc_id, n, sig, least, need, prefix): set size, digest of the set, its least shingle, l, and the rarest n - ceil(t n) + l shingles.

    l is a quarter of the shortest prefix, or all of it where the sketch expects more other holders of the
    prefix than it has shingles.
    """
    import zlib

    sent = docs.sparkSession.sparkContext.broadcast(zlib.compress(levels.tobytes(), 1))  # 4 MB at most before compression

    def run(batches):
        import hashlib
        import zlib

        import pyarrow as pa

        from zplane.llm.jaccard_join import _batched_sets
        from zplane.session import trim, worker_cache

        worker_cache(None)
        level = np.frombuffer(zlib.decompress(sent.value), np.uint8)
        for (ids,), sets in _batched_sets(batches, k, 1):
            n, sig, least, need, prefix = [], [], [], [], []
            for s in sets:
                n.append(len(s))
                least.append(int(s[:1].view(np.int64).sum()))
                sig.append(hashlib.blake2b(s.tobytes(), digest_size=16).digest())
                p = len(s) - needed(len(s), percent) + 1 if len(s) else 0
                of = level[(s >> np.uint64(64 - SKETCH_BITS)).astype(np.int64)]
                order = np.argsort(of, kind="stable")
                dear = (np.exp2(of[order[:p]]) - 1).sum() > p
                need.append(p if dear else (p + 3) // 4)
                prefix.append(s[order[: p + max(need[-1], 1) - 1]].view(np.int64))
            lens = np.cumsum([0, *map(len, prefix)])
            flat = np.concatenate([np.zeros(0, np.int64), *prefix])
            lists = pa.ListArray.from_arrays(pa.array(lens, pa.int32()), pa.array(flat, pa.int64()))
            yield pa.RecordBatch.from_arrays([ids, pa.array(n, pa.int64()), pa.array(sig, pa.binary()), pa.array(least, pa.int64()), pa.array(need, pa.int32()), lists], ["doc_id", "n", "sig", "least", "need", "prefix"])
        trim()

    return docs.mapInArrow(run, "doc_id long, n long, sig binary, least long, need int, prefix array<long>")


def _with_partners(sets: DataFrame) -> DataFrame:
    """The ids of sets (doc_id, need, prefix) that may have a link: those that share as many prefix
    shingles as they or any document they share one with ask for. Partial aggregates and a join that can
    be split keep frequent shingles out of single tasks; the shingles go in TURNS shares, one after the
    other, so that the shuffles of one share at a time lie on disk."""
    met = None
    for turn in range(TURNS):
        entries = sets.select("doc_id", "need", F.explode("prefix").alias("token")).where(F.pmod("token", F.lit(TURNS)) == turn)
        shared = entries.groupBy("token").agg(F.count("*").alias("holders"), F.min("need").alias("least")).where("holders > 1").select("token", "least")
        hits = stored(entries.join(shared, "token").groupBy("doc_id").agg(F.count("*").alias("hits"), F.min(F.least("need", "least")).alias("asked")), "hits")
        release(sets.sparkSession)
        met = hits if met is None else met.union(hits)
    return met.groupBy("doc_id").agg(F.sum("hits").alias("hits"), F.min("asked").alias("asked")).where("hits >= asked").select("doc_id")


class LocalJoin:
    """Links between sets in memory, as spanning edges; `first` marks the sets of the first block, `classes`
    names what is connected already."""

    def __init__(self, ids: list[int], sets: list[np.ndarray], percent: int, first: np.ndarray | None = None, classes: list[int] | None = None):
        order = sorted(range(len(ids)), key=lambda i: (len(sets[i]), ids[i]))
        self.ids, self.sets, self.percent = [ids[i] for i in order], [sets[i] for i in order], percent
        self.first = None if first is None else first[order]
        self.parent = list(range(len(ids)))
        if classes is not None:
            head: dict[int, int] = {}
            self.parent = [head.setdefault(classes[j], i) for i, j in enumerate(order)]
        self.edges: list[tuple[int, int]] = []

    def find(self, i: int) -> int:
        p = self.parent
        while p[i] != i:
            p[i] = p[p[i]]
            i = p[i]
        return i

    def _try(self, i: int, j: int, shared: int) -> None:
        if 100 * shared >= self.percent * (len(self.sets[i]) + len(self.sets[j]) - shared):
            a, b = self.find(i), self.find(j)
            if a != b:
                self.parent[max(a, b)] = min(a, b)
                self.edges.append((self.ids[i], self.ids[j]))

    def _pair_ok(self, i: int, j: int) -> bool:
        return self.first is None or self.first[i] != self.first[j]

    def run(self, most: int = 4) -> list[tuple[int, int]]:
        m = len(self.ids)
        if m <= 4:
            for i in range(m):
                for j in range(i):
                    if self._pair_ok(i, j) and self.find(i) != self.find(j) and 100 * len(self.sets[j]) >= self.percent * len(self.sets[i]):
                        self._try(i, j, len(np.intersect1d(self.sets[i], self.sets[j], assume_unique=True)))
            return self.edges
        size = np.array([len(s) for s in self.sets])
        owner = np.repeat(np.arange(m), size)
        token, at, freq = np.unique(np.concatenate(self.sets), return_inverse=True, return_counts=True)
        rank = np.empty(len(token), np.int64)
        rank[np.lexsort((token, freq))] = np.arange(len(token))
        at = rank[at]
        freq = np.sort(freq)
        order = np.lexsort((at, owner))
        tokens, start = at[order], np.concatenate([[0], np.cumsum(size)])
        base = size - (-(-self.percent * size // 100)) + 1
        # the cheapest l for every document: postings read, and candidates that share l of them, each verified at about 40 postings
        lens, low = np.ones(m, np.int64), None
        cost_upto = np.concatenate([[0], np.cumsum(freq[tokens] - 1)])
        for l in range(1, most + 1):
            end = np.minimum(start[:-1] + base + l - 1, start[1:])
            read = cost_upto[end] - cost_upto[start[:-1]]
            cost = read + 40 * np.minimum(read / l, m)
            better = (cost < low) & (base + l - 1 <= size) if low is not None else np.ones(m, bool)
            lens[better] = l
            low = np.where(better, cost, low) if low is not None else cost
        end = np.minimum(start[:-1] + base + lens - 1, start[1:])
        # postings of the prefixes and of whole sets, by token
        keep = np.arange(len(tokens)) < np.repeat(end, size)
        p_tok, p_doc = tokens[keep], np.repeat(np.arange(m), size)[keep]
        by = np.argsort(p_tok, kind="stable")
        p_tok, p_doc = p_tok[by], p_doc[by]
        p_at = np.searchsorted(p_tok, np.arange(len(token) + 1))
        all_doc = None
        for i in range(1, m):
            mine = tokens[start[i] : end[i]]
            lists = [p_doc[p_at[t] : p_at[t + 1]] for t in mine.tolist()]
            cand = np.concatenate(lists) if lists else np.zeros(0, np.int64)
            cand = cand[cand < i]
            if not len(cand):
                continue
            seen, n = np.unique(cand, return_counts=True)
            ok = (n >= np.minimum(lens[i], lens[seen])) & (100 * size[seen] >= self.percent * size[i])
            if self.first is not None:
                ok &= self.first[seen] != self.first[i]
            seen = seen[ok].tolist()
            root = self.find(i)
            seen = [j for j in seen if self.find(j) != root]
            if len(seen) > 24:  # one count of all shared shingles is cheaper than many intersections
                if all_doc is None:
                    full = np.argsort(tokens, kind="stable")
                    all_doc, all_at = np.repeat(np.arange(m), size)[full], np.searchsorted(tokens[full], np.arange(len(token) + 1))
                shared = np.bincount(np.concatenate([all_doc[all_at[t] : all_at[t + 1]] for t in tokens[start[i] : start[i + 1]].tolist()]), minlength=m)
                for j in seen:
                    if self.find(j) != self.find(i):
                        self._try(i, j, int(shared[j]))
            else:
                for j in seen:
                    if self.find(j) != self.find(i):
                        self._try(i, j, len(np.intersect1d(self.sets[i], self.sets[j], assume_unique=True)))
        return self.edges


def _solve(sets: DataFrame, percent: int) -> DataFrame:
    """Spanning links (a, b) of rows (grp, i, j, block, doc_id, s, cls) sorted by (grp, i, j)."""

    def run(batches):
        import pyarrow as pa

        from zplane.llm.jaccard_join import LocalJoin
        from zplane.session import trim, worker_cache

        worker_cache(None)

        def links(key, rows):
            first = np.array([r[0] == key[1] for r in rows]) if key[1] != key[2] else None
            return LocalJoin([r[1] for r in rows], [np.frombuffer(r[2], np.uint64) for r in rows], percent, first, [r[3] for r in rows]).run()

        key, rows = None, []
        for b in batches:
            out = []
            for grp, i, j, block, doc, s, cls in zip(*(c.to_pylist() for c in b.columns)):
                if (grp, i, j) != key:
                    if rows:
                        out += links(key, rows)
                    key, rows = (grp, i, j), []
                rows.append((block, doc, s, cls))
            yield _edges(pa, out)
        if rows:
            yield _edges(pa, links(key, rows))
        rows.clear()
        trim()

    return sets.mapInArrow(run, "a long, b long")


def _edges(pa, out):
    return pa.RecordBatch.from_arrays([pa.array([e[0] for e in out], pa.int64()), pa.array([e[1] for e in out], pa.int64())], ["a", "b"])


def jaccard_components(docs: DataFrame, k: int = 5, percent: int = 80, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, n_shingles, component_id): documents linked at 100 |A n B| >= percent |A u B|, by component.

    component_id is the smallest id reachable by links, the document's own included. Texts without words
    (null or empty too) have no shingles and no links. Rows with a null id take no part in links and have
    a null component. Rows that repeat an id count as one node. Other columns are not read.
    """
    spark = docs.sparkSession
    ship(spark)
    picked = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text"))
    levels = _levels(_sketch(picked, k))
    release(spark)
    profiles = stored(_profiles(picked, k, percent, levels), "profiles")
    linked = profiles.where("n > 0 and doc_id is not null")
    copied = stored(linked.groupBy("sig").agg(F.min("doc_id").alias("rep"), F.count("*").alias("rows")).where("rows > 1").drop("rows"), "copied")
    members = stored(linked.select("doc_id", "sig").join(copied, "sig").where("doc_id <> rep").distinct(), "members")
    reps = linked.join(members.select("doc_id", "sig"), ["doc_id", "sig"], "left_anti").dropDuplicates(["doc_id", "sig"])
    reps = stored(reps.select("doc_id", "need", "prefix"), "reps")
    sizes = stored(profiles.select("doc_id", "n", "least"), "sizes")
    discard(spark, profiles)  # the prefixes are in reps
    release(spark)
    kept = _survivors(reps, sizes.where("n > 0 and doc_id is not null"))
    release(spark)
    # written, so that the shuffle of all texts is gone before those that are left are dealt out and their keys made
    texts = stored(picked.join(kept.hint("shuffle_hash"), "doc_id").select("text", "doc_id", "least", "spot"), "texts")
    release(spark)
    stars = stored(_stars(texts.select("text", "doc_id", "least", "spot").repartition("least", "spot"), k, percent, levels), "stars")
    release(spark)
    groups = stored(components(stars), "groups").withColumnRenamed("node", "doc_id").withColumnRenamed("root", "grp")
    sized = groups.join(sizes.groupBy("doc_id").agg(F.max("n").alias("n")), "doc_id")
    total = sized.groupBy("grp").agg(F.sum("n").alias("load"), F.count("*").alias("holders"))
    # fewer documents are left than had sets made for the stars, so making theirs again beats keeping all
    todo = stored(texts.join(sized.join(total, "grp").hint("shuffle_hash"), "doc_id").select("text", "doc_id", "grp", "n", "least", "load", "holders"), "todo")
    discard(spark, texts)
    release(spark)
    known = _hub_links(todo, k, percent)
    edges = stored(_solve(_spread(todo, known, k), percent), "links")
    release(spark)
    # copies of one set are one component, so rows that repeat an id join what their texts join
    both = edges.union(members.select(F.col("doc_id").alias("a"), F.col("rep").alias("b")))
    both = both.union(known) if known is not None else both
    labels = components(both)
    out = sizes.select("doc_id", F.col("n").alias("n_shingles")).join(labels.withColumnRenamed("node", "doc_id"), "doc_id", "left")
    return out.select("doc_id", "n_shingles", F.coalesce("root", "doc_id").alias("component_id"))


def _survivors(reps: DataFrame, linked: DataFrame) -> DataFrame:
    """(doc_id, least, spot) of one document of each set that may have a link to another set; spot deals out crowds of one least shingle.

    reps is discarded; linked has the least shingle of every document with words.
    """
    spark = reps.sparkSession
    first = stored(reps.join(_with_partners(reps), "doc_id", "left_semi"), "entries")
    discard(spark, reps)
    release(spark)
    some = _with_partners(first)
    kept = stored(linked.groupBy("doc_id").agg(F.min("least").alias("least")).join(some, "doc_id", "left_semi"), "kept")
    discard(spark, first)
    crowds = kept.groupBy("least").agg(F.count("*").alias("n")).where(F.col("n") > CROWD)
    placed = kept.join(crowds, "least", "left")
    spot = F.when(F.col("n").isNull(), 0).otherwise(F.pmod(F.xxhash64("doc_id"), F.ceil(F.col("n") / CROWD)))
    return stored(placed.select("doc_id", "least", spot.cast("long").alias("spot")), "placed")


def _hub_links(todo: DataFrame, k: int, percent: int) -> DataFrame | None:
    """Verified links (a, b) to hubs in components of more than one block; None where there is no such component.

    A hub is the smallest id with the commonest least shingle of those not tied yet. Its text goes to every
    part of its component, so no component gathers in one task.
    """
    large = todo.where(F.col("load") > BLOCK_SHINGLES)
    if large.isEmpty():
        return None
    large = stored(large.withColumn("spots", F.ceil(F.col("holders") / CROWD)), "large")
    known, left = None, large

    def run(batches):
        import pyarrow as pa

        from zplane.llm.jaccard_join import _batched_sets
        from zplane.session import trim, worker_cache

        worker_cache(None)
        hubs: dict = {}
        for (grp, spot, mine, doc), sets in _batched_sets(batches, k, 4):
            out = []
            for g, p, is_hub, d, s in zip(grp.to_pylist(), spot.to_pylist(), mine.to_pylist(), doc.to_pylist(), sets):
                if is_hub:
                    hubs = {(g, p): (d, s)}  # rows are sorted, so one at a time
                    continue
                hub = hubs.get((g, p))
                if hub is None or hub[0] == d:
                    continue
                a, b = sorted((len(s), len(hub[1])))
                if 100 * a >= percent * b:
                    shared = len(np.intersect1d(s, hub[1], assume_unique=True))
                    if 100 * shared >= percent * (a + b - shared):
                        out.append((d, hub[0]))
            yield _edges(pa, out)
        hubs.clear()
        trim()

    for _ in range(HUB_ROUNDS):
        common = left.groupBy("grp", "least").agg(F.count("*").alias("c"), F.min("doc_id").alias("hub"))
        hubs = common.groupBy("grp").agg(F.min_by("hub", F.struct(-F.col("c"), "hub")).alias("hub"))
        sent = large.join(hubs.select(F.col("hub").alias("doc_id"), F.col("grp")), ["doc_id", "grp"], "left_semi").dropDuplicates(["doc_id"])
        sent = sent.withColumn("spot", F.explode(F.sequence(F.lit(0), F.col("spots") - 1))).withColumn("other", F.lit(False))
        asked = left.withColumn("spot", F.pmod(F.xxhash64("doc_id"), F.col("spots"))).withColumn("other", F.lit(True))
        rows = sent.unionByName(asked).repartition("grp", "spot").sortWithinPartitions("grp", "spot", "other", "doc_id")
        found = stored(rows.select("grp", "spot", ~F.col("other"), "doc_id", "text").mapInArrow(run, "a long, b long"), "hubs")
        known = found if known is None else known.union(found)
        done = known.select(F.col("a").alias("doc_id")).union(known.select("b")).union(hubs.select("hub"))
        left = large.join(done.distinct(), "doc_id", "left_anti")
    return known


def pair_prefix(n: int, percent: int) -> int:
    """Prefix length at which two linked sets must share two neighbours: with p(n) = n - needed + 1 and the
    largest partner's p', l = p + p' shared shingles can't all be parted by p + p' - 2 others. 0: n is too small."""
    p = n - needed(n, percent) + 1
    m = n * 100 // percent
    length = p + p + m - needed(m, percent) + 1 - 1
    return length if length <= n else 0


@lru_cache(maxsize=1 << 16)
def _partner_sizes(n: int, percent: int) -> tuple[bool, bool]:
    """Whether some partner no larger than n is too small for neighbours, and whether some is not."""
    fits = [pair_prefix(m, percent) > 0 for m in range(needed(n, percent), n + 1)]
    return not all(fits), any(fits)


def set_keys(s: np.ndarray, level: np.ndarray, percent: int) -> np.ndarray:
    """Keys of which two linked sets have one in common: neighbours in the prefixes for the smaller set's
    sake, and single shingles where a possible smaller partner is too small for that."""
    n = len(s)
    order = s[np.argsort(level[(s >> np.uint64(64 - SKETCH_BITS)).astype(np.int64)], kind="stable")]
    keys = []
    some_small, some_large = _partner_sizes(n, percent)
    if pair_prefix(n, percent):
        t = order[: pair_prefix(n, percent)]
        keys.append(sh.mix(t[:-1] * np.uint64(0x9E3779B97F4A7C15) + t[1:]))
    if some_small:
        keys.append(order[: n - needed(n, percent) + 1])
        if some_large and not pair_prefix(n, percent):
            keys.append(sh.mix(order[:-1] * np.uint64(0x9E3779B97F4A7C15) + order[1:]))
    return np.concatenate(keys) if keys else np.zeros(0, np.uint64)


def _stars(texts: DataFrame, k: int, percent: int, levels: np.ndarray) -> DataFrame:
    """Edges (a, b) from each set to the smallest id with the same key; a task sends on one id for each key."""
    import zlib

    sent = texts.sparkSession.sparkContext.broadcast(zlib.compress(levels.tobytes(), 1))

    def tied(key: np.ndarray, doc: np.ndarray):
        """The distinct keys, the root of each one's holders, and the links from every tied document to its root."""
        order = np.lexsort((doc, key))
        key, doc = key[order], doc[order]
        first = np.append(True, key[1:] != key[:-1]) if len(key) else np.zeros(0, bool)
        center = doc[np.maximum.accumulate(np.where(first, np.arange(len(key)), 0))] if len(key) else doc
        far = doc != center
        nodes, roots = union_find(doc[far], center[far])
        key, doc = key[first], doc[first]
        if len(nodes):
            i = np.minimum(np.searchsorted(nodes, doc), len(nodes) - 1)
            doc = np.where(nodes[i] == doc, roots[i], doc)
        off = nodes != roots
        return key, doc, nodes[off], roots[off]

    def local(batches):
        import zlib

        import pyarrow as pa

        from zplane.llm.jaccard_join import _batched_sets, set_keys
        from zplane.session import trim, worker_cache

        worker_cache(None)
        level = np.frombuffer(zlib.decompress(sent.value), np.uint8)
        for ids, sets in _batched_sets(batches, k, 0):
            keys = [set_keys(x, level, percent).view(np.int64) for x in sets]
            key, doc, node, root = tied(np.concatenate(keys), np.repeat(ids[0].to_numpy(), [len(x) for x in keys]))
            n, m = len(key), len(node)
            yield pa.RecordBatch.from_arrays([pa.array(np.concatenate([key, node])), pa.array(np.concatenate([doc, root])), pa.array(np.arange(n + m) >= n)], ["key", "doc", "link"])
        trim()

    def merge(batches):
        import pyarrow as pa

        from zplane.session import trim, worker_cache

        worker_cache(None)
        keys, docs, a, b = [], [], [], []
        for batch in batches:
            key, doc, link = (c.to_numpy(zero_copy_only=False) for c in batch.columns)
            keys.append(key[~link])
            docs.append(doc[~link])
            a.append(key[link])
            b.append(doc[link])
        if keys:
            _, _, node, root = tied(np.concatenate(keys), np.concatenate(docs))
            keys.clear(), docs.clear()
            nodes, roots = union_find(np.concatenate([*a, node]), np.concatenate([*b, root]))
            off = nodes != roots
            yield pa.RecordBatch.from_arrays([pa.array(nodes[off]), pa.array(roots[off])], ["a", "b"])
        trim()

    rows = texts.mapInArrow(local, "key long, doc long, link boolean")
    return rows.repartition("key").mapInArrow(merge, "a long, b long")


def _batched_sets(batches, k: int, text: int):
    """(other columns, shingle sets) of slices of about 2 MB of text (column number `text`)."""
    import pyarrow.compute as pc

    for b in batches:
        size = np.cumsum(pc.fill_null(pc.binary_length(b.column(text)), 0).to_numpy())
        lo = 0
        while lo < b.num_rows:
            before = int(size[lo - 1]) if lo else 0
            hi = max(lo + 1, int(np.searchsorted(size, before + (1 << 21), side="right")))
            texts = [sh.lowered(t) for t in b.column(text).slice(lo, hi - lo).to_pylist()]
            sets = [s for part in sh.in_groups(texts) for s in sh.shingle_sets(texts[part], k)]
            yield [c.slice(lo, hi - lo) for i, c in enumerate(b.columns) if i != text], sets
            lo = hi


def _with_sets(texts: DataFrame, k: int, keep: tuple[str, ...] = ()) -> DataFrame:
    """(doc_id, s, keep..) of rows (doc_id, text, keep..)."""

    def run(batches):
        import pyarrow as pa

        from zplane.llm.jaccard_join import _batched_sets
        from zplane.session import trim, worker_cache

        worker_cache(None)
        for (doc, *kept), sets in _batched_sets(batches, k, 1):
            yield pa.RecordBatch.from_arrays([doc, pa.array([s.tobytes() for s in sets], pa.binary()), *kept], ["doc_id", "s", *keep])
        trim()

    kinds = ", ".join(f"{f.name} {f.dataType.simpleString()}" for f in texts.schema.fields if f.name in keep)
    return texts.mapInArrow(run, "doc_id long, s binary" + (", " + kinds if keep else ""))


def _spread(todo: DataFrame, known: DataFrame | None, k: int) -> DataFrame:
    """Every set once for each pair of blocks that its own block is part of. A class of known links that is larger than a
    block has blocks of its own, which need no comparison with each other; all other sets share the rest."""
    rows = todo.select("doc_id", "grp", "n")
    if known is None:
        rows = rows.withColumn("cls", F.col("doc_id"))
    else:
        rows = rows.join(components(known).withColumnRenamed("node", "doc_id"), "doc_id", "left").withColumn("cls", F.coalesce("root", "doc_id")).drop("root")
    classes = stored(rows.groupBy("grp", "cls").agg(F.sum("n").alias("load")), "classes")
    own = classes.where(F.col("load") > BLOCK_SHINGLES).select("grp", "cls", F.ceil(F.col("load") / BLOCK_SHINGLES).alias("parts"))
    rest = classes.where(F.col("load") <= BLOCK_SHINGLES).groupBy("grp").agg(F.ceil(F.sum("load") / BLOCK_SHINGLES).alias("parts")).where("parts > 0")
    blocks = own.union(rest.select("grp", F.lit(None).cast("long"), "parts")).withColumn("at", F.explode(F.sequence(F.lit(0), F.col("parts") - 1)))
    blocks = blocks.select("grp", "cls", _block("cls", "at").alias("block"))
    a, b = blocks.toDF("grp", "x", "i"), blocks.toDF("grp", "y", "j")
    pairs = stored(a.join(b, "grp").where("i <= j and not (x is not null and x <=> y)").select("grp", "i", "j"), "pairs")
    placed = rows.join(own, ["grp", "cls"], "left").withColumnRenamed("parts", "mine").join(rest, "grp", "left")
    block = F.when(F.col("mine").isNotNull(), _block("cls", F.pmod(F.xxhash64("doc_id"), F.col("mine")))).otherwise(_block(F.lit(None), F.pmod(F.xxhash64("cls"), F.col("parts"))))
    placed = placed.select("doc_id", "grp", "cls", block.alias("block"))
    sides = pairs.select("grp", F.col("i").alias("block"), "i", "j").union(pairs.where("i <> j").select("grp", F.col("j").alias("block"), "i", "j"))
    # only documents of some pair have sets made
    asked = placed.join(sides.select("grp", "block").distinct(), ["grp", "block"], "left_semi")
    texts = todo.select("doc_id", "text").join(asked.hint("shuffle_hash"), "doc_id").select("doc_id", "text", "grp", "cls", "block")
    sets = _with_sets(texts, k, ("grp", "cls", "block"))
    rows = sets.join(sides, ["grp", "block"]).select("grp", "i", "j", "block", "doc_id", "s", "cls")
    return rows.repartition("grp", "i", "j").sortWithinPartitions("grp", "i", "j")


def _block(cls, at):
    """Name of a block: of a class, or of the rest."""
    return F.concat(F.coalesce((F.col(cls) if isinstance(cls, str) else cls).cast("string"), F.lit("")), F.lit("/"), (F.col(at) if isinstance(at, str) else at).cast("string"))


SQL = r"""
WITH RECURSIVE ws AS (
  SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x20\x09-\x0D]+') AS w
  FROM documents),
sets AS (
  SELECT doc_id, CASE WHEN len(w) = 0 THEN [] WHEN len(w) < 3 THEN [array_to_string(w, ' ')]
                      ELSE list_distinct(list_transform(range(1, len(w) - 1), lambda i: w[i] || ' ' || w[i + 1] || ' ' || w[i + 2])) END AS s FROM ws),
toks AS (SELECT doc_id, len(s) AS n, unnest(s) AS t FROM sets),
shared AS (
  SELECT a.doc_id AS x, b.doc_id AS y, count(*) AS o, any_value(a.n) AS nx, any_value(b.n) AS ny
  FROM toks a JOIN toks b ON a.t = b.t AND a.doc_id < b.doc_id GROUP BY 1, 2),
links AS (SELECT x, y FROM shared WHERE 100 * o >= 90 * (nx + ny - o)),
both_ways AS (SELECT x, y FROM links UNION ALL SELECT y, x FROM links),
reach(id, root) AS (
  SELECT doc_id, doc_id FROM documents
  UNION
  SELECT e.y, r.root FROM reach r JOIN both_ways e ON e.x = r.id WHERE r.root < e.y),
roots AS (SELECT id, min(root) AS root FROM reach GROUP BY id)
SELECT s.doc_id, CAST(len(s.s) AS BIGINT) AS n_shingles, r.root AS component_id FROM sets s JOIN roots r ON r.id = s.doc_id
"""
