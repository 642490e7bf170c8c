"""Operator 2, near-duplicates by an LSH forest.

A document's word shingles are hashed to a set; sets that are equal count once from here on.  A
signature of 128 minima is read in 32 rotated orders: each order is one tree of the forest, the
documents sorted by their signature from that rotation on.  Documents that share the first ``DEPTH``
values of an order are a region of its tree, and neighbours in a region are those with the longest
common prefix.

1. ``FIRST`` orders: each document meets its neighbour before it.  The pairs are as many as the
   rows, whatever a group's size; those whose signatures agree enough are confirmed on full sets.
   Components of confirmed links get their smallest doc_id.
2. All orders, but only regions whose members are in different components.  There a document meets
   the neighbours before it that are in other components: all of them in a region of up to
   ``REGION`` members, the next ``FEW`` by common prefix in a larger one.  Components are taken again.
3. Larger regions that are still open are compared to the end.  Open regions that share documents
   are a cluster, and its documents outside the largest component meet all members of other
   components, block by block inside tasks: by signature first, where each task returns a spanning
   forest of what may be alike, then by full sets within the trees of that forest, where it returns
   a spanning forest of what is alike.  No row is ever formed for a pair, and nothing is skipped.

Two documents of similarity 0.8 miss each other in all 32 trees with a chance of 5e-8, and agree in
fewer than ``LEAST`` of 128 values with a chance of 1e-8; nothing else loses a link.  Large regions
are sorted by range, so one region spreads over many tasks.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import BROADCAST_IDS, BROADCAST_ROWS, materialise, replicated, salted, scratch_scope, without_ids
from .words import blocks, per_document

SHINGLE = 5
SIMILARITY = 80  # percent
TREES, DEPTH, VALUES = 32, 4, 128
#: Signature values that two documents must share before their sets are compared.
LEAST = 76
#: Values after the prefix that order a region.
ORDER = 12
#: Orders that give the first candidates.
FIRST = 8
#: Members of a region that meet each other all, and neighbours that each meets in a larger one.
REGION, FEW = 64, 4
#: Shingles, and signatures, in a block, of which two meet in one task.
BLOCK, SIGNATURES = 50_000, 1_500
#: Set sizes in one band differ by less than this factor, so alike sets are in one band or in neighbours.
BAND = 1.26

#: Links that one task joins (some 20 MB); beyond, rounds of joins do.
LOCAL_LINKS = 100_000

_rng = np.random.default_rng(20240229)
_A = _rng.integers(0, 1 << 32, VALUES, dtype="uint32") | np.uint32(1)
_B = _rng.integers(0, 1 << 32, VALUES, dtype="uint32")
_POWERS = np.cumprod(np.full(64, 0xD6E8FEB86659FD93, "uint64"), dtype="uint64")


def _mixed(h: np.ndarray) -> np.ndarray:
    h = (h ^ (h >> np.uint64(32))) * np.uint64(0xD6E8FEB86659FD93)
    h = (h ^ (h >> np.uint64(32))) * np.uint64(0xC2B2AE3D27D4EB4F)
    return h ^ (h >> np.uint64(32))


def shingle_set(raw: bytes, k: int) -> np.ndarray:
    """Sorted distinct 64-bit hashes of the k-word shingles; of the whole sequence if it is shorter."""
    words = raw.lower().split()
    n = len(words)
    if not n:
        return np.empty(0, "uint64")
    ids = np.fromiter(map(xxhash.xxh3_64_intdigest, words), "uint64", n)
    m = min(n, k)
    total = np.full(n - m + 1, m, "uint64")
    for j in range(m):
        total += ids[j : n - m + 1 + j] * _POWERS[j]
    return np.unique(_mixed(total))


def signature(hashes: np.ndarray) -> bytes:
    """The low 16 bits of VALUES minima of 32-bit permutations."""
    low = hashes.astype("uint32")
    least = np.full(VALUES, 0xFFFFFFFF, "uint32")
    for at in range(0, low.size, 2048):
        block = np.multiply.outer(_A, low[at : at + 2048])
        block += _B[:, None]
        np.minimum(least, block.min(axis=1), out=least)
    return least.astype("<u2").tobytes()


def signatures(docs: DataFrame, k: int = SHINGLE) -> DataFrame:
    """(doc_id, n_shingles, set_a, set_b, sig): the set's size, a 128-bit digest of it, and its signature."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in blocks(batches):
            n, a, b, sig = [], [], [], []
            for text in batch.column("text").cast(pa.binary()).to_pylist():
                s = shingle_set(text or b"", k)
                n.append(s.size)
                first, second = _digest(s)
                a.append(first)
                b.append(second)
                sig.append(signature(s) if s.size else None)
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), pa.array(n, pa.int64()), pa.array(a, pa.int64()), pa.array(b, pa.int64()), pa.array(sig, pa.binary())], ["doc_id", "n_shingles", "set_a", "set_b", "sig"])

    return per_document(docs, run, "doc_id long, n_shingles long, set_a long, set_b long, sig binary")


def _digest(s: np.ndarray) -> tuple[int, int]:
    whole = xxhash.xxh3_128_digest(s.tobytes()) if s.size else bytes(16)
    return int.from_bytes(whole[:8], "little", signed=True), int.from_bytes(whole[8:], "little", signed=True)


def _speakers(signed: DataFrame) -> tuple[DataFrame, bool]:
    """One row per doc_id that isn't null, and whether any was repeated: the smallest set digest speaks for a repeated doc_id."""
    named = signed.where("doc_id is not null")
    several = named.groupBy("doc_id").agg(F.count("*").alias("__n"), F.min(F.struct("set_a", "set_b")).alias("__s")).where("__n > 1")
    several = materialise(several.select("doc_id", "__s.set_a", "__s.set_b"), "repeated")
    if several.isEmpty():
        return named, False
    few = F.broadcast(several) if several.limit(BROADCAST_IDS + 1).count() <= BROADCAST_IDS else several
    own = named.join(few, ["doc_id", "set_a", "set_b"], "left_semi").dropDuplicates(["doc_id"])
    return named.join(few, "doc_id", "left_anti").unionByName(own), True


def _collapsed(signed: DataFrame) -> DataFrame:
    """(doc_id, n_shingles, rep, sig): rep is the smallest doc_id of the equal sets, and only it keeps the signature."""
    key = ["set_a", "set_b", "n_shingles"]
    equal = signed.where("n_shingles > 0").groupBy(*key).agg(F.min("doc_id").alias("rep"), F.count("*").alias("__n")).where("__n > 1").drop("__n")
    joined = salted(signed, "doc_id").join(replicated(equal), [*key, "__salt"], "left").withColumn("rep", F.coalesce("rep", "doc_id"))
    return joined.select("doc_id", "n_shingles", "rep", F.when(F.col("rep") == F.col("doc_id"), F.col("sig")).alias("sig"))


def _values(tree: Column, first: int, n: int) -> Column:
    """Bytes of n values of a tree's order, which starts at value DEPTH * tree and goes round."""
    return F.substring(F.concat("sig", "sig"), F.lit(2) * (F.lit(DEPTH) * tree + first) + 1, F.lit(2 * n))


def _tree() -> Column:
    """A region's name has its tree in the last five bits."""
    return F.col("region").bitwiseAND(F.lit(TREES - 1)).cast("int")


def _tree_rows(reps: DataFrame) -> DataFrame:
    """(region, rep) for each document and tree."""
    named = lambda t: F.xxhash64(t, _values(t, 0, DEPTH)).bitwiseAND(F.lit(-TREES)).bitwiseOR(t.cast("long"))
    return reps.select(F.explode(F.transform(F.sequence(F.lit(0), F.lit(TREES - 1)), named)).alias("region"), "rep")


def _with_company(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Of rows in the order of regions, those whose neighbour is in the same region; the first and last row of a task stay besides."""
    held = None
    for batch in batches:
        if not batch.num_rows:
            continue
        table = pa.Table.from_batches([batch] if held is None else [held, batch]).combine_chunks()
        region = table.column("region").to_numpy()
        same = region[1:] == region[:-1]
        stay = np.concatenate([[held is None], same]) | np.concatenate([same, [False]])
        # the last row waits for its next neighbour; the first stays if it was held with a neighbour before it
        if held is not None:
            stay[0] |= bool(before)
        before = same[-1] if same.size else before if held is not None else True
        yield from table.slice(0, table.num_rows - 1).filter(pa.array(stay[:-1])).to_batches()
        held = table.slice(table.num_rows - 1).to_batches()[0]
    if held is not None:
        yield held


def forest(reps: DataFrame) -> DataFrame:
    """(region, rep) of all documents that have company in a region, and a few that have none."""
    rows = _tree_rows(reps)
    return rows.repartitionByRange("region", "rep").sortWithinPartitions("region", "rep").mapInArrow(_with_company, "region long, rep long")


def _meet(limit: int, least: int):
    """Arrow function over rows (region, rep, comp, n, sig) in the order of a tree: pairs (a, b) of neighbours in one
    region, at most ``limit`` places apart and of different components, with sizes and signatures that allow the similarity."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        tail: list[np.ndarray] | None = None
        for batch in batches:
            if not batch.num_rows:
                continue
            sig = np.frombuffer(b"".join(batch.column("sig").to_pylist()), "<u2").reshape(-1, VALUES)
            own = [*(batch.column(c).to_numpy() for c in ("region", "rep", "comp", "n")), sig]
            rows = own if tail is None else [np.concatenate(x) for x in zip(tail, own, strict=True)]
            new, (region, rep, comp, n, sig) = len(own[0]), rows
            old = len(region) - new
            found = [(np.empty(0, "int64"), np.empty(0, "int64"))]
            at = np.arange(max(old, 1), len(region))
            for j in range(1, limit + 1):
                at = at[at >= j]
                at = at[region[at] == region[at - j]]
                if not at.size:
                    break
                x = at[comp[at] != comp[at - j]]
                x = x[100 * np.minimum(n[x], n[x - j]) >= SIMILARITY * np.maximum(n[x], n[x - j])]
                for part in np.array_split(x, -(-x.size // 8192)) if x.size else ():
                    part = part[(sig[part] == sig[part - j]).sum(axis=1) >= least]
                    found.append((rep[part], rep[part - j]))
            a, b = (np.concatenate(c) for c in zip(*found, strict=True))
            yield pa.RecordBatch.from_arrays([pa.array(np.minimum(a, b)), pa.array(np.maximum(a, b))], ["a", "b"])
            tail = [x[-limit:] for x in rows]

    return run


def _neighbours(rows: DataFrame, reps: DataFrame, limit: int, by_range: bool) -> DataFrame:
    """Candidate pairs of rows (region, rep, comp); by_range spreads a region over tasks, else it is whole in one."""
    signed = rows.join(reps.select("rep", F.col("n_shingles").alias("n"), "sig"), "rep").withColumn("ord", _values(_tree(), DEPTH, ORDER))
    dealt = signed.repartitionByRange("region", "ord", "rep") if by_range else signed.repartition("region")
    ordered = dealt.sortWithinPartitions("region", "ord", "rep").select("region", "rep", "comp", "n", "sig")
    return ordered.mapInArrow(_meet(limit, LEAST), "a long, b long")


def _sets_of(docs: DataFrame, ids: DataFrame, k: int, repeated: bool) -> DataFrame:
    """(doc_id, shingles binary) of the documents named in ``ids``."""
    wanted = F.broadcast(ids) if ids.limit(BROADCAST_IDS + 1).count() <= BROADCAST_IDS else ids.hint("merge")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in blocks(batches):
            sets = [shingle_set(t or b"", k) for t in batch.column("text").cast(pa.binary()).to_pylist()]
            a, b = zip(*map(_digest, sets), strict=True)
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), pa.array(a, pa.int64()), pa.array(b, pa.int64()), pa.array([s.tobytes() for s in sets], pa.binary())], ["doc_id", "set_a", "set_b", "shingles"])

    sets = per_document(docs.join(wanted, "doc_id", "left_semi"), run, "doc_id long, set_a long, set_b long, shingles binary")
    if repeated:
        sets = sets.groupBy("doc_id").agg(F.min_by("shingles", F.struct("set_a", "set_b")).alias("shingles"))
    return sets.select("doc_id", "shingles")


def _confirm(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        found = []
        for x, y in zip(batch.column("x").to_pylist(), batch.column("y").to_pylist(), strict=True):
            x, y = np.frombuffer(x, "uint64"), np.frombuffer(y, "uint64")
            if x.size > y.size:
                x, y = y, x
            at = np.searchsorted(y, x)
            common = int((y[np.minimum(at, y.size - 1)] == x).sum())
            found.append(100 * common >= SIMILARITY * (x.size + y.size - common))
        yield pa.RecordBatch.from_arrays([batch.column("a"), batch.column("b")], ["a", "b"]).filter(pa.array(found, pa.bool_()))


def confirmed(docs: DataFrame, pairs: DataFrame, k: int, repeated: bool) -> DataFrame:
    """The pairs (a, b) whose full sets reach the similarity.  A document is in at most a few thousand pairs, so no key is hot."""
    ids = materialise(pairs.select(F.col("a").alias("doc_id")).union(pairs.select("b")).distinct(), "ids")
    sets = materialise(_sets_of(docs, ids, k, repeated), "sets")
    both = pairs.join(sets.select(F.col("doc_id").alias("a"), F.col("shingles").alias("x")), "a").join(sets.select(F.col("doc_id").alias("b"), F.col("shingles").alias("y")), "b")
    return materialise(both.select("a", "b", "x", "y").mapInArrow(_confirm, "a long, b long"), "links")


def _united(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """(rep, comp) of the ends of all links of a task."""
    above: dict[int, int] = {}

    def root(x: int) -> int:
        above.setdefault(x, x)
        while above[x] != x:
            above[x] = x = above[above[x]]
        return x

    for batch in batches:
        for u, v in zip(batch.column("u").to_pylist(), batch.column("v").to_pylist(), strict=True):
            u, v = sorted((root(u), root(v)))
            above[v] = u
    rep = sorted(above)
    yield pa.RecordBatch.from_arrays([pa.array(rep, pa.int64()), pa.array([root(x) for x in rep], pa.int64())], ["rep", "comp"])


def components(links: DataFrame) -> DataFrame:
    """(rep, comp): for each end of a link the smallest number that links reach, by alternating stars.

    A large star hangs a vertex's larger neighbours under its smallest one; a small star hangs
    the smaller ones and the vertex itself there.  Both keep components, and the edges end as stars.
    Up to ``LOCAL_LINKS`` links are joined in one task instead.
    """
    edges = materialise(links.select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v")).where("u > v").distinct(), "edges")
    if edges.count() <= LOCAL_LINKS:
        return materialise(edges.coalesce(1).mapInArrow(_united, "rep long, comp long"), "united")
    while True:
        both = edges.union(edges.select(F.col("v").alias("u"), F.col("u").alias("v")))
        least = both.groupBy("u").agg(F.min("v").alias("m"))
        large = both.where("v > u").join(least, "u").select(F.col("v").alias("u"), F.least("m", "u").alias("v"))
        large = materialise(large.distinct(), "large-star")
        least = large.groupBy("u").agg(F.min("v").alias("m"))
        small = large.join(least, "u")
        small = small.select(F.col("v").alias("u"), F.col("m").alias("v")).where("u > v").union(least.select("u", F.col("m").alias("v"))).distinct()
        new = materialise(small, "small-star")
        # done when every edge hangs under a vertex that hangs nowhere and hangs there alone
        stars = new.join(new.select(F.col("u").alias("v")), "v", "left_semi").isEmpty() and new.groupBy("u").count().where("count > 1").isEmpty()
        if stars:
            return new.select(F.col("u").alias("rep"), F.col("v").alias("comp")).union(new.select(F.col("v").alias("rep"), F.col("v").alias("comp")).distinct())
        edges = new


def open_regions(level: DataFrame, labels: DataFrame) -> DataFrame:
    """Rows of the regions whose members are in different components, with members (their number), lead (the smallest) and comp."""
    named = salted(level.join(labels, "rep", "left").withColumn("comp", F.coalesce("comp", "rep")), "rep")
    regions = named.groupBy("region").agg(F.count("*").alias("members"), F.min("rep").alias("lead"), F.min("comp").alias("__lo"), F.max("comp").alias("__hi"))
    return named.join(replicated(regions.where("__lo < __hi")), ["region", "__salt"]).select("rep", "region", "members", "lead", "comp")


def _forest_of_signatures(job: pa.Table) -> pa.Table:
    """A spanning forest (a, b) of outsiders (side 0) and members (side 1) that may be alike by their signatures."""
    rep, side, n, comp = (job.column(c).to_numpy() for c in ("rep", "side", "n_shingles", "comp"))
    sig = np.frombuffer(b"".join(job.column("sig").to_pylist()), "<u2").reshape(-1, VALUES)
    o, m = np.flatnonzero(side == 0), np.flatnonzero(side == 1)
    alike = np.zeros((o.size, m.size), "uint8")
    for own, theirs in zip(sig[o].T, sig[m].T, strict=True):
        alike += own[:, None] == theirs
    may = (alike >= LEAST) & (comp[o][:, None] != comp[m]) & (100 * np.minimum(n[o][:, None], n[m]) >= SIMILARITY * np.maximum(n[o][:, None], n[m]))
    found: list[tuple[int, int]] = []
    left, free = may.any(axis=1), np.ones(m.size, bool)
    for start in np.flatnonzero(left):
        if not left[start]:
            continue
        left[start] = False
        todo = [start]
        while todo:  # breadth first: each new member under the outsider that found it, each new outsider under a member
            x = todo.pop()
            new = np.flatnonzero(may[x] & free)
            free[new] = False
            found += [(rep[o[x]], rep[m[y]]) for y in new]
            for y in new:
                more = np.flatnonzero(may[:, y] & left)
                left[more] = False
                found += [(rep[o[z]], rep[m[y]]) for z in more]
                todo += more.tolist()
    a, b = (pa.array([int(x[k]) for x in found], pa.int64()) for k in (0, 1))
    return pa.table({"a": a, "b": b})


def _forest_of_links(job: pa.Table) -> pa.Table:
    """A spanning forest (a, b) of the alike sets of different components, of outsiders (side 0) with members (side 1)."""
    rep, side = job.column("rep").to_numpy(), job.column("side").to_numpy()
    _, group = np.unique(job.column("comp").to_numpy(), return_inverse=True)
    sets = [np.frombuffer(x, "uint64") for x in job.column("shingles").to_pylist()]
    inside = np.flatnonzero(side == 1)
    sizes = np.array([sets[i].size for i in inside], "int64")
    found: list[tuple[int, int]] = []
    if inside.size:
        values = np.concatenate([sets[i] for i in inside])
        order = np.argsort(values, kind="stable")
        values, holder = values[order], np.repeat(np.arange(inside.size), sizes)[order]
        for o in np.flatnonzero(side == 0):
            first, last = np.searchsorted(values, sets[o], "left"), np.searchsorted(values, sets[o], "right")
            n = last - first
            at = np.arange(n.sum()) + np.repeat(first - (np.cumsum(n) - n), n)
            common = np.bincount(holder[at], minlength=inside.size)
            alike = inside[100 * common >= SIMILARITY * (sets[o].size + sizes - common)]
            roots, one = np.unique(group[alike], return_index=True)
            new = roots != group[o]
            found += [(int(rep[o]), int(rep[i])) for i in alike[one[new]]]
            if new.any():
                group[np.isin(group, roots[new])] = group[o]
    a, b = (pa.array([x[k] for x in found], pa.int64()) for k in (0, 1))
    return pa.table({"a": a, "b": b})


def _across_blocks(named: DataFrame, load: Column, block: int, payload: str, kernel) -> DataFrame:
    """Links (a, b) from ``kernel``, which sees the blocks of each cluster's outsiders with those of its members, two at a time.

    ``named`` has cluster, rep, comp, n_shingles and the ``payload`` column.  Outsiders are the
    documents outside the cluster's largest component.  A block holds documents of one band of set
    sizes with ``load`` summing to about ``block``.
    """
    per_comp = named.groupBy("cluster", "comp").count()
    main = per_comp.groupBy("cluster").agg(F.max_by("comp", F.struct("count", "comp")).alias("main"), F.count("*").alias("comps")).where("comps > 1").drop("comps")
    band = F.floor(F.log("n_shingles") / F.lit(float(np.log(BAND)))).cast("int")
    members = salted(named, "rep").join(replicated(main), ["cluster", "__salt"]).drop("__salt")
    sides = F.when(F.col("comp") == F.col("main"), F.array(F.lit(1))).otherwise(F.array(F.lit(0), F.lit(1)))
    sided = members.select("cluster", "rep", "comp", "n_shingles", band.alias("band"), F.explode(sides).alias("side"))
    key = ["cluster", "side", "band"]
    parts = materialise(sided.groupBy(*key).agg(F.ceil(F.sum(load) / block).alias("parts")), "parts")
    # the parts of a band are numbered, so a pair of them is a job
    numbered = salted(sided, "rep").join(replicated(parts), [*key, "__salt"]).withColumn("block", F.pmod(F.xxhash64("rep"), F.col("parts"))).drop("__salt", "parts")
    numbers = parts.select(*key, F.explode(F.sequence(F.lit(0).cast("long"), F.col("parts") - 1)).alias("block"))
    own = numbers.where("side = 0").select("cluster", F.col("band").alias("band0"), F.col("block").alias("block0"), F.explode(F.array(*[F.col("band") + d for d in (-1, 0, 1)])).alias("band1"))
    theirs = numbers.where("side = 1").select("cluster", F.col("band").alias("band1"), F.col("block").alias("block1"))
    jobs = materialise(own.join(theirs, ["cluster", "band1"]).select("cluster", "band0", "block0", "band1", "block1"), "jobs")
    loaded = materialise(numbered.join(named.select("rep", payload), "rep"), "blocks")
    job = ["cluster", "band0", "block0", "band1", "block1"]
    rows = [
        loaded.where(F.col("side") == s).withColumnsRenamed({"band": f"band{s}", "block": f"block{s}"}).join(jobs, ["cluster", f"band{s}", f"block{s}"]).select(*job, "side", "rep", "comp", "n_shingles", payload)
        for s in (0, 1)
    ]
    return materialise(rows[0].unionByName(rows[1]).groupBy(*job).applyInArrow(kernel, "a long, b long"), "forest")


def large_region_links(docs: DataFrame, open_: DataFrame, reps: DataFrame, k: int, repeated: bool = False) -> DataFrame | None:
    """Links (a, b) that join the components which alike members of open regions are in; None where none can be alike."""
    clusters = components(open_.select(F.col("rep").alias("a"), F.col("lead").alias("b"))).withColumnRenamed("comp", "cluster")
    named = materialise(open_.select("rep", "comp").distinct().join(clusters, "rep").join(reps, "rep"), "clusters")
    may = _across_blocks(named, F.lit(1), SIGNATURES, "sig", _forest_of_signatures)
    if may.isEmpty():
        return None
    narrow = components(may).withColumnRenamed("comp", "cluster")
    sets = materialise(_sets_of(docs, narrow.select(F.col("rep").alias("doc_id")), k, repeated), "large-sets").withColumnRenamed("doc_id", "rep")
    narrowed = materialise(named.drop("cluster", "sig").join(narrow, "rep").join(sets, "rep"), "narrowed")
    return _across_blocks(narrowed, F.col("n_shingles"), BLOCK, "shingles", _forest_of_links)


def _labels(docs: DataFrame, reps: DataFrame, k: int, repeated: bool) -> DataFrame:
    """(rep, comp) of all documents with links."""
    level = materialise(forest(reps), "forest")
    alone = level.where(_tree() < FIRST).withColumn("comp", F.col("rep"))
    tested = materialise(_neighbours(alone, reps, 1, True).distinct(), "first")
    links = confirmed(docs, tested, k, repeated)
    labels = materialise(components(links), "labels", keep=True)
    open_ = materialise(open_regions(level, labels), "open")
    near = _neighbours(open_.where(F.col("members") <= REGION), reps, REGION, False).union(_neighbours(open_.where(F.col("members") > REGION), reps, FEW, True))
    more = materialise(near.distinct().join(tested, ["a", "b"], "left_anti"), "second")
    if not more.isEmpty():
        links = links.union(confirmed(docs, more, k, repeated))
        labels = materialise(components(links), "labels", keep=True)
    large = open_.where(F.col("members") > REGION).select("rep", "region")
    if not large.isEmpty():
        still = materialise(open_regions(large, labels), "large")
        dense = None if still.isEmpty() else large_region_links(docs, still, reps, k, repeated)
        if dense is not None and not dense.isEmpty():
            labels = materialise(components(links.union(dense)), "labels", keep=True)
    return labels


def near_duplicates(docs: DataFrame, k: int = SHINGLE) -> DataFrame:
    """One row per input row: doc_id, n_shingles (of its own text), component_id, kept.

    A document without words has an empty set and is linked with nothing, so it stays.  Repeated
    rows of one doc_id share their decision, which is taken on the one with the smallest set digest.
    A row with a null doc_id is linked with nothing: its component_id is null and it stays.  An
    empty table gives an empty result; further columns are ignored.
    """
    spark = docs.sparkSession
    with scratch_scope(spark):
        signed = materialise(signatures(docs, k), "signed", keep=True)
        speakers, repeated = _speakers(signed)
        base = materialise(_collapsed(speakers), "collapsed")
        labels = _labels(docs, base.where("sig is not null").select("rep", "n_shingles", "sig"), k, repeated)
        decided = materialise(salted(base.drop("sig"), "doc_id").join(replicated(labels), ["rep", "__salt"], "left").select("doc_id", "n_shingles", F.coalesce("comp", "rep").alias("component_id")), "decided", keep=True)
    if repeated:
        decided = signed.where("doc_id is not null").select("doc_id", "n_shingles").join(decided.drop("n_shingles"), "doc_id")
    out = decided.select("doc_id", "n_shingles", "component_id", (F.col("doc_id") == F.col("component_id")).alias("kept"))
    nameless = signed.where("doc_id is null").select("doc_id", "n_shingles", F.lit(None).cast("long").alias("component_id"), F.lit(True).alias("kept"))
    return out.unionByName(nameless)


def drop_near_duplicates(docs: DataFrame, k: int = SHINGLE) -> DataFrame:
    """The rows of ``docs`` that stay, one document for each component, with their own columns."""
    with scratch_scope(docs.sparkSession):
        dropped = materialise(near_duplicates(docs, k).where("not kept").select(F.col("doc_id").alias("__id")).distinct(), "dropped", keep=True)
    return without_ids(docs, dropped)
