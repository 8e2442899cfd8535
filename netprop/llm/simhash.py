"""SimHash near-duplicates by generalised pigeonhole search over Hamming space.

A text becomes one 64-bit fingerprint: the majority vote, bit by bit, of the
XXH64 values of its word shingles. Fingerprints within ``radius`` bits link.

Search. The bits are grouped into partitions so that correlated bits stay
together, and each partition i gets its own radius t_i (-1: not probed) with
sum(t_i) = radius - partitions + 1. If every partition differed by more than its
t_i the total would exceed ``radius``, so some partition is within t_i: no link
is lost. The number of partitions and the t_i come from a dynamic programme over
estimated cost (probes sent plus pairs met), with statistics over all
fingerprints. Equal fingerprints are collapsed first, so groups of copies cost
one row; buckets that stay large are split again by the pigeonhole principle on
the remaining bits. Buckets give spanning edges only, never all pairs.
"""

from __future__ import annotations

import functools
import itertools
import math

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, functions as F

from netprop.llm import common

BITS = 64
#: Cost of one probe row against one compared pair (rows are shuffled, pairs are one xor and popcount).
PROBE_COST = 40.0
#: Members above which a bucket is split again on its remaining bits.
HOT_MEMBERS = 4096
#: Times that a bucket is split at most.
SPLITS = 3
#: Pairs that a task expands at once.
PAIR_CHUNK = 1 << 21

_LOWER = bytes(b + 32 if 65 <= b <= 90 else b for b in range(256))


# ------------------------------------------------------------- fingerprints


def shingle_hashes(text: bytes, width: int) -> list[int]:
    import xxhash

    digest = xxhash.xxh64_intdigest
    words = text.translate(_LOWER).split()  # bytes.split() parts at 0x20 and 0x09-0x0D only
    if not words:
        return []
    if len(words) <= width:
        return [digest(b" ".join(words), 42)]
    ends = np.cumsum(np.fromiter(map(len, words), np.int64, len(words)) + 1) - 1
    starts = np.concatenate([[0], ends[:-1] + 1])
    line = b" ".join(words)
    return [digest(line[s:e], 42) for s, e in zip(starts[: len(words) - width + 1].tolist(), ends[width - 1 :].tolist(), strict=True)]


def majority(hashes: np.ndarray, lengths: np.ndarray) -> np.ndarray:
    """Fingerprint of each run of ``lengths`` hashes; empty runs give zero."""
    out = np.zeros(len(lengths), np.uint64)
    full = np.flatnonzero(lengths)
    if len(full):
        starts = np.concatenate([[0], np.cumsum(lengths[full])[:-1]])
        bits = np.unpackbits(hashes.astype("<u8").view(np.uint8).reshape(-1, 8), axis=1, bitorder="little")
        votes = np.add.reduceat(bits, starts, axis=0, dtype=np.int64)
        out[full] = np.packbits(votes * 2 > lengths[full][:, None], axis=1, bitorder="little").view("<u8").ravel()
    return out


def fingerprint_text(text: bytes | None, width: int = 4) -> int:
    return int(_fingerprints([text], width)[0])


def _fingerprints(texts: list[bytes | None], width: int, once: bool = False, flush: int = 1 << 18) -> np.ndarray:
    out, held, lengths = [], [], []

    def drain():
        if lengths:
            out.append(majority(np.array(held, np.uint64), np.array(lengths, np.int64)))
            held.clear(), lengths.clear()

    for text in texts:
        found = shingle_hashes(text or b"", width)
        if once:
            found = list(dict.fromkeys(found))
        if len(found) > flush:  # a very long text votes in parts
            drain()
            votes = np.zeros(BITS, np.int64)
            for i in range(0, len(found), flush):
                part = np.array(found[i : i + flush], np.uint64)
                votes += np.unpackbits(part.astype("<u8").view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(0, dtype=np.int64)
            out.append(np.packbits(votes * 2 > len(found), bitorder="little").view("<u8"))
            continue
        held += found
        lengths.append(len(found))
        if len(held) > flush:
            drain()
    drain()
    return np.concatenate(out) if out else np.zeros(0, np.uint64)


def fingerprinted(rows: DataFrame, width: int = 4) -> DataFrame:
    """``rows`` with their last column, the text as bytes, turned into ``fp``: one signed LONG. Null texts count as empty (zero)."""
    kept = rows.schema.fields[:-1]

    def run(batches):
        for batch in batches:
            fps = _fingerprints(batch.column(len(kept)).to_pylist(), width)
            yield pa.RecordBatch.from_arrays([*batch.columns[:-1], pa.array(fps.view(np.int64))], names=[*[f.name for f in kept], "fp"])

    return rows.mapInArrow(run, ", ".join([f"`{f.name}` {f.dataType.simpleString()}" for f in kept] + ["fp long"]))


def fingerprints(docs: DataFrame, width: int = 4, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``(doc_id, fp)`` of each row."""
    return fingerprinted(docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("binary").alias("text")), width)


# ------------------------------------------------------------------- planning


def bit_statistics(fps: DataFrame) -> tuple[int, np.ndarray]:
    """Count of fingerprints and the 64 x 64 matrix of how often two bits are both set, over all."""

    def run(batches):
        total, n = np.zeros((BITS, BITS)), 0
        for batch in batches:
            x = np.asarray(batch.column(0).to_numpy(zero_copy_only=False), np.int64)
            for i in range(0, len(x), 1 << 16):
                bits = np.unpackbits(x[i : i + (1 << 16)].astype("<i8").view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").astype(np.float32)
                total += bits.T @ bits
            n += len(x)
        i, j = np.triu_indices(BITS)
        if n:
            yield pa.RecordBatch.from_arrays([pa.array(np.append(i, -1)), pa.array(np.append(j, -1)), pa.array(np.append(total[i, j].astype(np.int64), n))], names=["i", "j", "n"])

    rows = fps.select("fp").mapInArrow(run, "i long, j long, n long").groupBy("i", "j").agg(F.sum("n").alias("n")).collect()  # 2081 rows at most
    both, n = np.zeros((BITS, BITS)), 0
    for r in rows:
        if r.i < 0:
            n = r.n
        else:
            both[r.i, r.j] = both[r.j, r.i] = r.n
    return n, both


def correlation(n: int, both: np.ndarray) -> np.ndarray:
    p = np.diag(both) / max(n, 1)
    spread = np.sqrt(np.maximum(p * (1 - p), 1e-12))
    return np.abs((both / max(n, 1) - np.outer(p, p)) / np.outer(spread, spread))


def group_bits(corr: np.ndarray, parts: int) -> list[list[int]]:
    """Equal-sized groups; each grows from a free bit by the one most correlated with it."""
    left, out = set(range(BITS)), []
    for i in range(parts):
        size = BITS // parts + (i < BITS % parts)
        seed = max(left, key=lambda b: (corr[b, sorted(left - {b})].max() if len(left) > 1 else 0, -b))
        group = [seed]
        left.discard(seed)
        while len(group) < size:
            best = max(left, key=lambda b: (corr[b, group].mean(), -b))
            group.append(best)
            left.discard(best)
        out.append(sorted(group))
    return out


def within(p: np.ndarray, group: list[int], upto: int) -> np.ndarray:
    """Chance that two fingerprints differ in at most 0, 1, ... ``upto`` bits of the group, bits taken as independent."""
    mass = np.zeros(upto + 1)
    mass[0] = 1.0
    for b in group:
        d = 2 * p[b] * (1 - p[b])
        mass[1:] = mass[1:] * (1 - d) + mass[:-1] * d
        mass[0] *= 1 - d
    return np.cumsum(mass)


def ball(size: int, radius: int) -> int:
    return sum(math.comb(size, r) for r in range(radius + 1))


def allocate(costs: list[list[float]], total: int) -> tuple[float, list[int]]:
    """costs[i][t + 1]: cost of radius t in partition i. Cheapest radii that sum to ``total``, each -1 or more."""
    reach: dict[int, tuple[float, list[int]]] = {0: (0.0, [])}
    for row in costs:
        step: dict[int, tuple[float, list[int]]] = {}
        for spent, (cost, chosen) in reach.items():
            for t in range(-1, len(row) - 1):
                new = (cost + row[t + 1], [*chosen, t])
                if (at := spent + t) not in step or new < step[at]:
                    step[at] = new
        reach = step
    return reach[total]


def same_value_pairs(fps: DataFrame, plans: list[list[list[int]]]) -> dict[tuple[int, int], float]:
    """For each group of each plan: pairs of fingerprints that agree on all its bits, counted over all."""
    cells = [F.struct(F.lit(k).alias("k"), F.lit(i).alias("i"), F.col("fp").bitwiseAND(F.lit(signed(mask_of(g)))).alias("v")) for k, plan in enumerate(plans) for i, g in enumerate(plan)]
    counts = fps.select(F.explode(F.array(*cells)).alias("c")).groupBy("c.k", "c.i", "c.v").count()
    rows = counts.groupBy("k", "i").agg(F.sum(F.col("count").cast("double") * (F.col("count") - 1) / 2).alias("pairs")).collect()
    return {(r.k, r.i): r.pairs for r in rows}


def mask_of(group: list[int]) -> int:
    return sum(1 << b for b in group)


def signed(x: int) -> int:
    return x - (1 << 64) if x >= 1 << 63 else x


def plan_search(fps: DataFrame, radius: int = 4) -> dict:
    """Partitions and radii of least estimated cost, from statistics over all fingerprints."""
    n, both = bit_statistics(fps)
    p, corr = np.diag(both) / max(n, 1), correlation(n, both)
    pairs = n * (n - 1) / 2

    def priced(group: list[int], scale: float) -> list[float]:
        met = np.minimum(within(p, group, radius) * scale, 1.0) * pairs
        return [0.0] + [PROBE_COST * n * ball(len(group), t) + met[t] for t in range(radius + 1)]

    drafts = []
    for parts in range(2, radius + 2):
        groups = group_bits(corr, parts)
        drafts.append((allocate([priced(g, 1.0) for g in groups], radius - parts + 1)[0], groups))
    least = min(c for c, _ in drafts)
    plans = [g for c, g in drafts if c <= 6 * least]
    agree = same_value_pairs(fps, plans)
    best = None
    for k, groups in enumerate(plans):
        scales = [max(1.0, agree.get((k, i), 0.0) / max(pairs * within(p, g, 0)[0], 1e-9)) for i, g in enumerate(groups)]
        found = allocate([priced(g, s) for g, s in zip(groups, scales, strict=True)], radius - len(groups) + 1)
        if best is None or found[0] < best[0]:
            best = (*found, groups)
    return {"n": n, "cost": best[0], "radii": best[1], "groups": best[2], "radius": radius}


# ------------------------------------------------------------------ candidates


def _others(fps: DataFrame) -> list[str]:
    return ["root"] if "root" in fps.columns else []


def probe_rows(fps: DataFrame, plan: dict) -> DataFrame:
    """``(part, key, fp)`` and what else ``fps`` has: every fingerprint under its own value in each probed partition and under those near it."""
    out, more = None, _others(fps)
    for i, (group, t) in enumerate(zip(plan["groups"], plan["radii"], strict=True)):
        if t < 0:
            continue
        flips = [signed(mask_of(list(c))) for r in range(t + 1) for c in itertools.combinations(group, r)]
        own = F.col("fp").bitwiseAND(F.lit(signed(mask_of(group))))
        rows = fps.select(F.lit(i).alias("part"), own.alias("own"), "fp", *more, F.explode(F.array(*map(F.lit, flips))).alias("flip"))
        rows = rows.select("part", F.col("own").bitwiseXOR(F.col("flip")).alias("key"), "fp", *more)
        out = rows if out is None else out.unionByName(rows)
    return out


def split_hot(rows: DataFrame, plan: dict, hot_members: int, levels: int = SPLITS) -> DataFrame:
    """Rows of buckets with very many members go to finer buckets, again and again.

    Fingerprints that link differ in ``radius`` bits at most, so of any radius + 1 groups of
    the bits that a bucket has not used yet they agree on one. ``path`` says which groups a
    bucket was split by (a number per level), ``bits`` holds the values they agree on.
    """
    parts = plan["radius"] + 1
    free = {i: [b for b in range(BITS) if b not in group] for i, group in enumerate(plan["groups"])}
    rows = rows.withColumn("member", _member(plan)).withColumn("path", F.col("part")).withColumn("bits", F.lit(0).cast("long"))
    bucket = ["part", "key", "path", "bits"]
    done = None
    for _ in range(levels):
        hot = common.checkpointed(rows.where("member").groupBy(*bucket).count().where(F.col("count") > hot_members).select(*bucket, F.lit(True).alias("hot")))
        if common.is_empty(hot):
            break
        met = common.stored(rows.join(hot, bucket, "left"), "split")
        cold = met.where("hot is null").drop("hot")
        done = cold if done is None else done.unionByName(cold)
        spots, finer = None, {}
        for path, bits in free.items():
            masks = [bits[j::parts] for j in range(parts)]
            cells = F.array(*[F.struct(F.lit(path * (parts + 1) + len(free) + j).alias("path"), F.col("fp").bitwiseAND(F.lit(signed(mask_of(m)))).bitwiseOR(F.col("bits")).alias("bits")) for j, m in enumerate(masks)])
            finer |= {path * (parts + 1) + len(free) + j: [b for b in bits if b not in m] for j, m in enumerate(masks)}
            spots = F.when(F.col("path") == path, cells) if spots is None else spots.when(F.col("path") == path, cells)
        held = ["part", "key", "fp", *_others(rows), "member"]
        rows = met.where("hot").select(*held, F.explode(spots).alias("c")).select(*held, "c.path", "c.bits")
        free = finer
    return rows if done is None else done.unionByName(rows)


def _member(plan: dict):
    own = None
    for i, group in enumerate(plan["groups"]):
        value = F.col("fp").bitwiseAND(F.lit(signed(mask_of(group))))
        own = F.when(F.col("part") == i, value) if own is None else own.when(F.col("part") == i, value)
    return own == F.col("key")


def _cells(fps: DataFrame, plan: dict, hot_members: int) -> DataFrame:
    """``(cell, fp, member)`` and what else ``fps`` has: the buckets, each whole in one task and in one piece."""
    rows = split_hot(probe_rows(fps, plan), plan, hot_members)
    rows = rows.select(F.xxhash64("part", "key", "path", "bits").alias("cell"), "fp", "member", *_others(fps))
    return rows.repartition("cell").sortWithinPartitions("cell")


def _runs(batches):
    """Batches of whole cells, as lists of arrays."""
    held = []
    for batch in itertools.chain(batches, [None]):
        if batch is not None:
            if not batch.num_rows:
                continue
            held.append([np.asarray(batch.column(i).to_numpy(zero_copy_only=False)) for i in range(batch.num_columns)])
            if held[0][0][0] == held[-1][0][-1]:
                continue  # still the one cell: nothing is copied before it ends
        if not held:
            continue
        columns = list(map(np.concatenate, zip(*held, strict=True)))
        upto = len(columns[0]) if batch is None else int(np.searchsorted(columns[0], columns[0][-1]))
        held = [[c[upto:] for c in columns]] if batch is not None else []
        yield [c[:upto] for c in columns]


def spanning_links(fps: DataFrame, plan: dict, hot_members: int = HOT_MEMBERS) -> DataFrame:
    """``(a, b)``: links that join all fingerprints which any bucket links, each to a root of its task."""
    radius = plan["radius"]

    def run(batches):
        edges, n = [], 0

        def out():
            nodes, roots = local_components(*map(np.concatenate, zip(*edges, strict=True)))
            edges.clear()
            keep = nodes != roots
            return pa.RecordBatch.from_arrays([pa.array(nodes[keep]), pa.array(roots[keep])], names=["a", "b"])

        for cell, fp, member in _runs(batches):
            for a, b, _ in bucket_links(cell, fp, member.astype(bool), radius):
                edges.append((a, b))
                n += len(a)
            if n > 1 << 20:
                yield out()
                n = 0
        if edges:
            yield out()

    return _cells(fps.select("fp"), plan, hot_members).mapInArrow(run, "a long, b long")


local_components = common.local_components


def bucket_links(cell: np.ndarray, fp: np.ndarray, member: np.ndarray, radius: int, root: np.ndarray | None = None):
    """Links within each run of equal ``cell`` (sorted), as arrays of pairs and whether they are all. Compares probes with members.

    Without ``root`` a large bucket gives links that join what it links; with it all links between different roots come.
    """
    if not len(cell):
        return
    starts = np.flatnonzero(np.append(True, cell[1:] != cell[:-1]))
    sizes = np.diff(np.append(starts, len(cell)))
    mates = np.add.reduceat(member, starts, dtype=np.int64)
    big = sizes * mates > PAIR_CHUNK
    for i in np.flatnonzero(big):
        s = slice(starts[i], starts[i] + sizes[i])
        if root is None:
            yield from _flood(fp[s], member[s], radius)
        else:
            yield from _every(fp[s], member[s], root[s], radius)
    few = np.flatnonzero((mates > 0) & (sizes > 1) & ~big)
    if not len(few):
        return
    group = np.repeat(np.arange(len(starts)), sizes)
    at = np.flatnonzero(member)
    first = np.searchsorted(at, starts)
    bounds = np.flatnonzero(np.diff(np.append(-1, np.cumsum(sizes[few] * mates[few]) // PAIR_CHUNK)))
    for lo, hi in itertools.pairwise([*bounds.tolist(), len(few)]):
        some = np.zeros(len(starts), bool)
        some[few[lo:hi]] = True
        rows = np.flatnonzero(some[group])
        m = mates[group[rows]]
        left = np.repeat(rows, m)
        right = at[np.repeat(first[group[rows]], m) + np.arange(len(left)) - np.repeat(np.cumsum(m) - m, m)]
        a, b = fp[left], fp[right]
        near = (a != b) & (np.bitwise_count((a ^ b).view(np.uint64)) <= radius)
        if root is not None:
            near &= root[left] != root[right]
        if near.any():
            yield a[near], b[near], True


def _every(fp: np.ndarray, member: np.ndarray, root: np.ndarray, radius: int):
    """All links between different roots in a large bucket, a block of its members at a time."""
    at = np.flatnonzero(member)
    step = max(1, PAIR_CHUNK // len(fp))
    for i in range(0, len(at), step):
        some = at[i : i + step]
        bits = np.bitwise_count((fp[some, None] ^ fp).view(np.uint64))
        x, y = np.nonzero((bits > 0) & (bits <= radius) & (root[some, None] != root))
        if len(x):
            yield fp[some[x]], fp[y], True


def _flood(fp: np.ndarray, member: np.ndarray, radius: int):
    """Breadth-first search in a large bucket: each text met leaves the set that others are compared with."""
    left, where = np.unique(fp, return_index=True)
    own = np.zeros(len(left), bool)
    own[np.searchsorted(left, fp[member])] = True
    seeds = left[own]
    free = left
    for seed in seeds:
        at = np.searchsorted(free, seed)
        if at == len(free) or free[at] != seed:
            continue
        free = np.delete(free, at)
        queue = [seed]
        while queue:
            x = queue.pop()
            near = np.bitwise_count((free ^ x).view(np.uint64)) <= radius
            if near.any():
                met = free[near]
                free = free[~near]
                queue.extend(met)
                yield np.full(len(met), x), met, False


# -------------------------------------------------------------------- operator


def near_duplicates(docs: DataFrame, width: int = 4, radius: int = 4, id_col: str = "doc_id", text_col: str = "text", hot_members: int = HOT_MEMBERS) -> DataFrame:
    """``(doc_id, fingerprint, component_id)``, one row per input row.

    Null and empty texts have fingerprint zero and link like any other. Repeated
    rows each come back with the same component. Null ids take part but never
    name a component (a component of null ids alone has a null id). An empty
    table gives an empty result; other columns of ``docs`` are ignored.
    """
    prints = common.stored(fingerprints(docs, width, id_col, text_col), "fingerprints")
    fps = common.stored(prints.groupBy("fp").agg(F.min("doc_id").alias("low"), F.count("*").alias("copies")), "distinct")
    rooted = classes(fps, radius, hot_members)
    names = rooted.groupBy("root").agg(F.min("low").alias("component_id"))
    named = rooted.join(names, "root").select("fp", "component_id", "copies")
    text = F.lpad(F.lower(F.hex("fp")), 16, "0").alias("fingerprint")
    return prints.join(named, "fp").select("doc_id", text, "component_id", "copies")


def classes(fps: DataFrame, radius: int = 4, hot_members: int = HOT_MEMBERS) -> DataFrame:
    """Distinct fingerprints ``fp`` (and what else ``fps`` has) with ``root``, one fingerprint of those reachable by links."""
    if common.is_empty(fps):
        return fps.withColumn("root", F.col("fp"))
    links = spanning_links(fps.select("fp"), plan_search(fps, radius), hot_members)
    roots = common.connected_components(links).withColumnRenamed("id", "fp")
    return fps.join(roots, "fp", "left").withColumn("root", F.coalesce("root", "fp"))


# ------------------------------------------------- similarity of word shingles

#: Words in the shingles whose distinct set is fingerprinted for probing, and bits by which fingerprints of like texts may differ.
#: At a five-word similarity of 0.8 about six bits differ, nine or fewer with a chance of 0.93; of such pairs of 10,000 given documents 0.99 were within nine.
#: (Of five-word fingerprints about ten bits differ: none of those pairs was within four.)
PROBE_WIDTH, PROBE_RADIUS = 2, 9
#: Texts in a block of a group of candidates, blocks after which a group gets larger ones, and shingles in a block.
BLOCK_ROWS, BLOCKS, BLOCK_SHINGLES = 64, 32, 1 << 20
#: Groups of one block hold texts of fewer than 2 ** (SHORT_K + 1) shingles.
SHORT_K = 13
#: Longs in the sketch of a set of shingles.
SKETCH_LONGS = 16
#: Least similarity (Jaccard) of two texts' sets of shingles.
SIMILARITY = 0.8


def word_prints(rows: DataFrame) -> DataFrame:
    """``rows`` with their last column, the text as bytes, turned into ``w1, w2`` (128 bits of its words) and ``fp`` (of its distinct PROBE_WIDTH-word shingles)."""
    kept = rows.schema.fields[:-1]

    def run(batches):
        import xxhash

        for batch in batches:
            texts = [t or b"" for t in batch.column(len(kept)).to_pylist()]
            words = np.frombuffer(b"".join(xxhash.xxh3_128_digest(b" ".join(t.translate(_LOWER).split())) for t in texts), ">i8").astype(np.int64).reshape(-1, 2)
            fps = _fingerprints(texts, PROBE_WIDTH, True)
            yield pa.RecordBatch.from_arrays([*batch.columns[:-1], pa.array(words[:, 0]), pa.array(words[:, 1]), pa.array(fps.view(np.int64))], names=[*[f.name for f in kept], "w1", "w2", "fp"])

    return rows.mapInArrow(run, ", ".join([f"`{f.name}` {f.dataType.simpleString()}" for f in kept] + ["w1 long, w2 long, fp long"]))


def shingle_sets(rows: DataFrame, width: int) -> DataFrame:
    """``rows`` with their last column, the text as bytes, turned into ``shingles``, its distinct shingles as 32 bits of their hashes, and ``sketch``, where their number is odd."""
    kept = rows.schema.fields[:-1]

    def run(batches):
        bits = 64 * SKETCH_LONGS
        for batch in batches:
            sets = [np.unique(np.array(shingle_hashes(t or b"", width), np.uint64).astype(np.uint32).view(np.int32)) for t in batch.column(len(kept)).to_pylist()]
            offsets = np.cumsum([0, *map(len, sets)]).astype(np.int32)
            odd = [np.packbits((np.bincount(s.view(np.uint32) % bits, minlength=bits) & 1).astype(bool)).view(np.int64) for s in sets]
            places = np.arange(0, (len(sets) + 1) * SKETCH_LONGS, SKETCH_LONGS).astype(np.int32)
            columns = [pa.ListArray.from_arrays(pa.array(offsets), pa.array(np.concatenate([*sets, np.zeros(0, np.int32)]))), pa.ListArray.from_arrays(pa.array(places), pa.array(np.concatenate([*odd, np.zeros(0, np.int64)])))]
            yield pa.RecordBatch.from_arrays([*batch.columns[:-1], *columns], names=[*[f.name for f in kept], "shingles", "sketch"])

    return rows.mapInArrow(run, ", ".join([f"`{f.name}` {f.dataType.simpleString()}" for f in kept] + ["shingles array<int>, sketch array<long>"]))


def alike(edges: DataFrame, sets: DataFrame, similarity: float) -> DataFrame:
    """The edges ``(a, b)`` whose nodes' ``(node, shingles)`` have at least this similarity."""
    of = lambda end: sets.select(F.col("node").alias(end), F.col("shingles").alias(f"s_{end}"))
    both = F.size(F.array_intersect("s_a", "s_b"))
    return edges.join(of("a"), "a").join(of("b"), "b").where(both >= similarity * (F.size("s_a") + F.size("s_b") - both)).select("a", "b")


def maybe_alike(edges: DataFrame, sets: DataFrame, similarity: float) -> DataFrame:
    """The edges ``(a, b)`` that sizes and sketches leave open; no pair of this similarity is lost.

    A sketch holds, bit by bit, whether an odd number of the set's shingles fall there. Where
    two differ, some shingle is in one set only, so sets differ in no fewer shingles than sketches in bits.
    """
    of = lambda end: sets.select(F.col("node").alias(end), F.size("shingles").alias(f"n_{end}"), F.col("sketch").alias(f"k_{end}"))
    bits = functools.reduce(Column.__add__, [F.bit_count(F.col("k_a")[i].bitwiseXOR(F.col("k_b")[i])) for i in range(SKETCH_LONGS)])
    apart, both = F.greatest(bits, F.abs(F.col("n_a") - F.col("n_b"))), F.col("n_a") + F.col("n_b")
    return edges.join(of("a"), "a").join(of("b"), "b").where(both - apart >= similarity * (both + apart) - 1e-6).select("a", "b")


def blocked(sets: DataFrame) -> DataFrame:
    """``sets`` (a stored table with ``group`` and its number of nodes, ``rows``) with ``k`` and ``block``: what of a group is compared at once.

    ``k`` is the whole logarithm of the set's size. A group of few short texts is one block;
    others are numbered by size, and a block holds BLOCK_ROWS, more where the group is very
    large, and BLOCK_SHINGLES at most (or one text).
    """
    n = F.size("shingles")
    k = F.floor(F.log2(F.greatest(n, F.lit(1)) + 0.5)).cast("int")
    few = F.col("rows") <= BLOCK_ROWS
    sets = sets.withColumn("k", F.when(few, F.greatest(k, F.lit(SHORT_K))).otherwise(k)).withColumn("n", n)
    one = few & (F.col("k") == SHORT_K)
    easy, hard = sets.where(one).withColumn("block", F.lit(0).cast("long")), sets.where(~one)
    if common.is_empty(hard):
        return easy.drop("n")
    at = common.gapless_rank(hard.withColumn("part", F.xxhash64("group", "k")), "part", "n", "at", ("node",))
    most = F.greatest(F.lit(1), F.least(F.greatest(F.lit(BLOCK_ROWS), F.floor(F.col("rows") / BLOCKS)), F.floor(BLOCK_SHINGLES / F.pow(F.lit(2.0), F.col("k") + 1))))
    return easy.unionByName(at.withColumn("block", F.floor(F.col("at") / most).cast("long")).drop("part", "at")).drop("n")


def tiles(sets: DataFrame, similarity: float) -> DataFrame:
    """``(tile, side, node, fp, shingles, sketch)``: each pair of blocks of a group that may hold sets of this similarity, whole in one task and in one piece.

    Side 0 is to be compared with side 1, side 2 with itself.
    """
    sets = common.stored(blocked(sets), "blocks")
    blocks = sets.select("group", "k", "block").distinct()
    x, y = (blocks.select("group", F.col("k").alias(f"k_{e}"), F.col("block").alias(f"b_{e}")) for e in "xy")
    reach = math.ceil(-math.log2(similarity)) if similarity > 0 else BITS  # sizes of alike sets differ by a factor of 1 / similarity at most
    pairs = x.join(y, "group").where(f"k_y > k_x and k_y <= k_x + {reach} or k_y = k_x and b_y >= b_x")
    same = F.expr("k_y = k_x and b_y = b_x")
    left = F.struct(F.col("k_x").alias("k"), F.col("b_x").alias("block"), F.when(same, 2).otherwise(0).alias("side"))
    right = F.struct(F.col("k_y").alias("k"), F.col("b_y").alias("block"), F.lit(1).alias("side"))
    ends = pairs.select("group", F.xxhash64("group", "k_x", "b_x", "k_y", "b_y").alias("tile"), F.explode(F.when(same, F.array(left)).otherwise(F.array(left, right))).alias("e"))
    ends = ends.select("group", "e.k", "e.block", "tile", "e.side")
    dealt = sets.join(ends, ["group", "k", "block"]).select("tile", "side", "node", "fp", "shingles", "sketch")
    return dealt.repartition("tile").sortWithinPartitions("tile", "side")


def alike_links(sets: DataFrame, radius: int, similarity: float) -> DataFrame:
    """``(a, b)``: links that join all nodes of a group which pairs join that have fingerprints within ``radius`` and sets of this similarity.

    Every such pair of ``(node, fp, group, rows, shingles, sketch)`` is verified in the task that holds its tile,
    but for those that its links have joined by then; a task gives spanning links only, so no row stands for a pair compared.
    """

    def run(batches):
        for table in _whole(batches):
            tile, side, node, fp = (table.column(i).to_numpy() for i in range(4))
            shingles, sketch = (pa.concat_arrays(table.column(i).chunks) for i in (4, 5))
            ends = np.cumsum([0, *np.diff(shingles.offsets.to_numpy())])
            values, sketch = shingles.flatten().to_numpy(), sketch.flatten().to_numpy().reshape(-1, SKETCH_LONGS)
            edges = []
            for s, e in itertools.pairwise([*np.flatnonzero(np.append(True, tile[1:] != tile[:-1])).tolist(), len(tile)]):
                a, b = tile_links(side[s:e], fp[s:e], values[ends[s] : ends[e]], ends[s : e + 1] - ends[s], sketch[s:e], radius, similarity)
                edges.append((node[s:e][a], node[s:e][b]))
            nodes, roots = local_components(*map(np.concatenate, zip(*edges, strict=True)))
            keep = nodes != roots
            yield pa.RecordBatch.from_arrays([pa.array(nodes[keep]), pa.array(roots[keep])], names=["a", "b"])

    return tiles(sets, similarity).mapInArrow(run, "a long, b long")


def _whole(batches):
    """Tables of whole tiles."""
    held = []
    for batch in itertools.chain(batches, [None]):
        if batch is not None:
            if not batch.num_rows:
                continue
            held.append(batch)
            if held[0].column(0)[0].as_py() == batch.column(0)[-1].as_py():
                continue  # still the one tile: nothing is copied before it ends
        if not held:
            continue
        table = pa.Table.from_batches(held)
        tile = table.column(0).to_numpy()
        upto = len(tile) if batch is None else int(np.searchsorted(tile, tile[-1]))
        held = table.slice(upto).to_batches() if batch is not None else []
        yield table.slice(0, upto)


def tile_links(side: np.ndarray, fp: np.ndarray, values: np.ndarray, ends: np.ndarray, sketch: np.ndarray, radius: int, similarity: float) -> tuple[np.ndarray, np.ndarray]:
    """Places (a, b) of spanning links of a tile: row i has the set ``values[ends[i] : ends[i + 1]]``; rows of side 0 come before those of side 1."""
    size, label = np.diff(ends), np.arange(len(fp))
    words, code = np.unique(values, return_inverse=True)
    held, right, out = np.zeros(len(words), bool), np.flatnonzero(side != 0), []
    for x in np.flatnonzero(side != 1).tolist():
        y = right[np.searchsorted(right, x, "right") :]
        y = y[(label[y] != label[x]) & (np.bitwise_count((fp[y] ^ fp[x]).view(np.uint64)) <= radius)]
        if len(y):  # what sizes and sketches leave open, as in maybe_alike
            bits = np.bitwise_count((sketch[y] ^ sketch[x]).view(np.uint64)).sum(1, dtype=np.int64)
            apart, both = np.maximum(bits, np.abs(size[y] - size[x])), size[y] + size[x]
            y = y[both - apart >= similarity * (both + apart) - 1e-6]
        if not len(y):
            continue
        own = code[ends[x] : ends[x + 1]]
        held[own] = True
        for some in np.array_split(y, 1 + int(size[y].sum()) // PAIR_CHUNK):
            starts = np.cumsum(size[some]) - size[some]
            at = np.arange(size[some].sum()) + np.repeat(ends[some] - starts, size[some])
            both = np.bincount(np.repeat(np.arange(len(some)), size[some]), held[code[at]], len(some))
            for z in some[both >= similarity * (size[x] + size[some] - both)].tolist():
                if label[z] != label[x]:
                    out.append((x, z))
                    label[label == label[z]] = label[x]
        held[own] = False
    a, b = np.array(out, np.int64).reshape(-1, 2).T
    return a, b


def representatives(docs: DataFrame, width: int = 5, similarity: float = SIMILARITY, id_col: str = "doc_id", text_col: str = "text", radius: int = PROBE_RADIUS, hot_members: int = HOT_MEMBERS) -> DataFrame:
    """The rows of ``docs`` that stay when of each class of near-duplicates one does: that of the smallest id (null ids last), then of the smallest hash of id and text.

    Two texts link if their sets of ``width``-word shingles are similar by ``similarity`` or
    more. Candidates are found as always, by the generalised pigeonhole search over
    fingerprints (of word pairs, which a changed word moves less). Its spanning links make
    groups, outside of which no two fingerprints are near. The texts of a group are compared
    block by block: all pairs of near fingerprints are verified on the shingles, but for
    those between texts that verified links of the same blocks have joined.

    Rows are told apart by id and text, so unrelated rows of one id or without an id all
    stay. Of rows equal in both, the one with the smallest hash of all columns stays.
    Texts without words are alike.
    """
    own = (F.xxhash64(F.lit(1), id_col, text_col).alias("_k1"), F.xxhash64(F.lit(2), text_col, id_col).alias("_k2"))
    body = F.col(text_col).cast("binary").alias("_text")
    prints = common.stored(word_prints(docs.select(F.col(id_col).cast("long").alias("_id"), *own, body)), "fingerprints")
    order = F.struct(F.col("_id").isNull().alias("no"), F.col("_id"), F.col("_k1"), F.col("_k2"))
    nodes = prints.groupBy("w1", "w2").agg(F.first("fp").alias("fp"), F.min(order).alias("first")).withColumn("node", F.monotonically_increasing_id())
    nodes = common.stored(nodes.drop("w1", "w2"), "nodes")
    if common.is_empty(nodes):
        return docs.select("*")
    fps = common.stored(nodes.groupBy("fp").agg(F.count("*").alias("nodes")), "distinct")
    near = common.stored(classes(fps, radius, hot_members).withColumnRenamed("root", "group"), "groups")
    rows = near.groupBy("group").agg(F.sum("nodes").alias("rows")).where("rows > 1")
    met = nodes.join(near.join(rows, "group").select("fp", "group", "rows"), "fp").select("node", "fp", "group", "rows", "first._k1", "first._k2")
    texts = docs.select(*own, body).join(met, ["_k1", "_k2"]).select("node", "fp", "group", "rows", "_text").dropDuplicates(["node"])
    sets = common.stored(shingle_sets(texts, width), "shingles")
    links = common.stored(alike_links(sets, radius, similarity), "links")
    roots = common.connected_components(links).withColumnRenamed("id", "node")
    chosen = nodes.join(roots, "node", "left").groupBy(F.coalesce("root", "node")).agg(F.min("first").alias("first")).select("first._k1", "first._k2")
    chosen = common.stored(chosen, "chosen")
    twice = common.checkpointed(prints.join(chosen, ["_k1", "_k2"], "left_semi").groupBy("_k1", "_k2").count().where("count > 1").select("_k1", "_k2"))
    kept = docs.withColumns({"_k1": own[0], "_k2": own[1]}).join(chosen, ["_k1", "_k2"], "left_semi")
    if common.is_empty(twice):
        return kept.select(*docs.columns)
    every = F.struct(*[F.col(f"`{c}`") for c in docs.columns])
    rest = kept.join(twice, ["_k1", "_k2"], "left_semi").groupBy("_k1", "_k2").agg(F.min_by(every, F.xxhash64(F.to_json(every))).alias("row")).select("row.*")
    return kept.join(twice, ["_k1", "_k2"], "left_anti").select(*docs.columns).unionByName(rest)
