"""Removal of repeated byte strings by interval expansion on a Burrows-Wheeler transform.

Every byte covered by a ``length``-byte string that also starts earlier (smaller
document id, or same document and smaller offset) is removed; all strings are
judged on the input.

One transform of 100 TB is out of reach of one machine, so strings that may be
equal are brought together first. Each window of ``length`` bytes is represented
by its anchor, the ``ANCHOR``-byte string in it with the smallest hash (leftmost
of equals): equal windows have equal anchors at equal offsets. The windows of a
document that share one anchor form a segment. Per anchor:

1. Segments with equal bytes collapse to the earliest one, first within each
   map task, then across tasks; of the others all windows are repeats. So a
   passage in a third of all documents costs one entry per map task.
2. Where an anchor still has different segments, their bytes are gathered, and a
   bounded-context Burrows-Wheeler transform over them is searched breadth first:
   from the interval of all suffixes, backward extension by every character that
   occurs yields the intervals of strings one character longer; an interval whose
   right border has no common-prefix value yet gives it its length. Borders thus
   get their values in increasing order, and the search stops at ``length``:
   borders without a value part nothing, and the suffixes between two borders
   share ``length`` bytes. The earliest window of each such class stays.
3. An anchor with very many different segments (text around a very common
   phrase) is re-keyed by longer cores, which spreads it over many groups.

Documents are read three times; what travels is about 20 bytes an anchor (one in
some 35 bytes), the bytes of doubtful segments, and the texts twice.
"""

from __future__ import annotations

import hashlib
import itertools

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, functions as F

from netprop.llm import common

LENGTH = 100
ANCHOR = 32
#: Bytes hashed at once; longer texts are cut with an overlap of length - 1.
PIECE = 1 << 20
#: Different segments of one anchor above which it is re-keyed by longer cores.
HOT_SEGMENTS = 512
#: Window starts that share one core when re-keyed (cores have length - CORE_SPAN + 1 bytes).
CORE_SPAN = 8
#: Bytes in one transform, unless one group has more.
TEXT_CHUNK = 1 << 22
#: Bytes of text whose entries make one bucket, about.
BUCKET_BYTES = 64 << 20
#: Entries that a map task holds before it hands them on.
FLUSH = 1 << 19

_BASE = 0x9E3779B97F4A7C15 | 1
_MIX = np.uint64(0xD6E8FEB86659FD93)
_KEY_BITS = np.uint64((1 << 48) - 1)
_powers: dict[int, tuple[np.ndarray, np.ndarray]] = {}


def _power_tables(n: int) -> tuple[np.ndarray, np.ndarray]:
    size = 1 << max(12, int(n).bit_length())
    if size not in _powers:
        _powers.clear()
        inverse = pow(_BASE, -1, 1 << 64)
        with np.errstate(over="ignore"):
            up, down = (np.multiply.accumulate(np.concatenate([np.ones(1, np.uint64), np.full(size - 1, x, np.uint64)])) for x in (np.uint64(_BASE), np.uint64(inverse)))
        _powers[size] = up, down
    return _powers[size]


def window_hashes(data: np.ndarray, width: int) -> np.ndarray:
    """A 64-bit hash of each ``width``-byte string of ``data``."""
    n = len(data)
    if n < width:
        return np.zeros(0, np.uint64)
    up, down = _power_tables(n + 1)
    sums = np.zeros(n + 1, np.uint64)
    np.cumsum((data.astype(np.uint64) + np.uint64(1)) * up[:n], out=sums[1:])
    h = (sums[width:] - sums[:-width]) * down[: n - width + 1]
    h ^= h >> np.uint64(32)
    h *= _MIX
    h ^= h >> np.uint64(29)
    return h


def sliding_argmin(h: np.ndarray, width: int) -> np.ndarray:
    """Position of the smallest value (leftmost of equals) in each run of ``width`` values; 41 bits of a value are compared."""
    n = len(h)
    key = (h >> np.uint64(23) << np.uint64(23)) | np.arange(n, dtype=np.uint64)
    pad = -n % width
    blocks = np.concatenate([key, np.full(pad, np.iinfo(np.uint64).max, np.uint64)]).reshape(-1, width)
    ahead = np.minimum.accumulate(blocks, axis=1).ravel()
    back = np.minimum.accumulate(blocks[:, ::-1], axis=1)[:, ::-1].ravel()
    return (np.minimum(back[: n - width + 1], ahead[width - 1 : n]) & np.uint64((1 << 23) - 1)).astype(np.int64)


def segments(data: np.ndarray, ends: np.ndarray, length: int, anchor: int):
    """Segments of the texts that stand back to back in ``data``, text i ending at ``ends[i]``.

    Returns text number, first byte, end, anchor position (all within ``data``) and anchor hash.
    """
    starts = np.concatenate([[0], ends[:-1]])
    if len(data) < length:
        return (np.zeros(0, np.int64),) * 4 + (np.zeros(0, np.uint64),)
    h = window_hashes(data, anchor)
    at = sliding_argmin(h, length - anchor + 1)
    step = np.zeros(len(data) + 1, np.int32)
    fits = ends - starts >= length
    np.add.at(step, starts[fits], 1)
    np.add.at(step, ends[fits] - length + 1, -1)
    valid = np.flatnonzero(np.cumsum(step[: len(at)]))
    spot = at[valid]
    cut = np.flatnonzero(np.append(True, (spot[1:] != spot[:-1]) | (valid[1:] != valid[:-1] + 1)))
    first, last = valid[cut], valid[np.append(cut[1:] - 1, len(valid) - 1)]
    text = np.searchsorted(ends, first, side="right")
    return text, first, last + length, spot[cut], h[spot[cut]]


def _content_keys(raw: bytes, first: np.ndarray, ends: np.ndarray) -> np.ndarray:
    import xxhash

    digest, view = xxhash.xxh3_64_intdigest, memoryview(raw)
    return np.array([digest(view[a:b]) for a, b in zip(first.tolist(), ends.tolist(), strict=True)], np.uint64) & _KEY_BITS


def _pieces(batches, length: int):
    """(bytes, per-piece doc, rep, offset, end in bytes): whole texts gathered up to PIECE bytes, longer ones cut with overlap."""
    held, size = [], 0

    def out():
        docs, reps, offs, parts = zip(*held, strict=True)
        return b"".join(parts), np.array(docs, np.int64), np.array(reps, np.int64), np.array(offs, np.int64), np.cumsum([len(p) for p in parts])

    for batch in batches:
        for doc, rep, text in zip(*(batch.column(i).to_pylist() for i in range(3)), strict=True):
            if text is None or len(text) < length:
                continue
            for off in range(0, len(text) - length + 1, PIECE - length + 1):
                part = text[off : off + PIECE]
                if held and size + len(part) > PIECE:
                    yield out()
                    held, size = [], 0
                held.append((doc, rep, off, part))
                size += len(part)
    if held:
        yield out()


def _first_of_each(*keys: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Order by the keys (first counts most); where a new value of the first two begins, in that order."""
    order = np.lexsort(keys[::-1])
    a, b = keys[0][order], keys[1][order]
    return order, np.append(True, (a[1:] != a[:-1]) | (b[1:] != b[:-1]))


# ------------------------------------------------------------ packed entries
# An entry: key and content (48 bits each), doc, rep, first byte, bytes, anchor offset.

_FIELDS = (("key", "<u8"), ("content", "<u8"), ("doc", "<i8"), ("rep", "<i4"), ("first", "<i8"), ("size", "<u2"), ("lead", "<u2"))


def pack(entry: dict[str, np.ndarray]) -> bytes:
    """Columns one after the other; ids as differences, numbers in as few bytes as the largest needs."""
    out = [len(entry["key"]).to_bytes(4, "little")]
    for name, kind in _FIELDS:
        x = entry[name].astype(np.int64) if name not in ("key", "content") else entry[name].astype("<u8")
        base = 0
        if name == "doc" and len(x):
            base, x = int(x[0]), np.diff(x, prepend=x[:1])
        width = 6 if name in ("key", "content") else 8 if len(x) and x.min() < 0 else next(w for w in (1, 2, 4, 8) if not len(x) or x.max() < 1 << (8 * w - 1))
        out.append(bytes([width]) + base.to_bytes(8, "little", signed=True) + np.ascontiguousarray(x.astype("<i8" if kind != "<u8" else "<u8").view(np.uint8).reshape(-1, 8)[:, :width]).T.tobytes())
    return b"".join(out)


def unpack(raw: bytes) -> dict[str, np.ndarray]:
    n, at, entry = int.from_bytes(raw[:4], "little"), 4, {}
    for name, _ in _FIELDS:
        width, base = raw[at], int.from_bytes(raw[at + 1 : at + 9], "little", signed=True)
        x = np.zeros((n, 8), np.uint8)
        x[:, :width] = np.frombuffer(raw, np.uint8, n * width, at + 9).reshape(width, n).T
        x = x.view("<u8" if name in ("key", "content") else "<i8").ravel()
        entry[name] = np.cumsum(x) + base if name == "doc" else x
        at += 9 + n * width
    return entry


def _join(entries: list[dict[str, np.ndarray]]) -> dict[str, np.ndarray]:
    return {name: np.concatenate([e[name] for e in entries]) for name, _ in _FIELDS}


def _take(entry: dict[str, np.ndarray], rows) -> dict[str, np.ndarray]:
    return {k: v[rows] for k, v in entry.items()}


def _collapse(entry: dict[str, np.ndarray]) -> tuple[dict[str, np.ndarray], dict[str, np.ndarray]]:
    """Earliest entry of each (key, content), in order of key; and the others, whose windows are repeats."""
    order, new = _first_of_each(entry["key"], entry["content"], entry["doc"], entry["rep"], entry["first"])
    return _take(entry, order[new]), _take(entry, order[~new])


def merge_ranges(doc, rep, first, ends):
    """Union of [first, ends) within each (doc, rep); touching ranges become one."""
    if not len(doc):
        return doc, rep, first, ends
    order = np.lexsort((first, rep, doc))
    doc, rep, first, ends = doc[order], rep[order], first[order], ends[order]
    new_doc = np.append(True, (doc[1:] != doc[:-1]) | (rep[1:] != rep[:-1]))
    rank = np.cumsum(new_doc)
    lift = rank * (int(ends.max()) + 1)
    reach = np.maximum.accumulate(ends + lift)
    start = np.append(True, first[1:] + lift[1:] > reach[:-1])
    at = np.flatnonzero(start)
    return doc[at], rep[at], first[at], reach[np.append(at[1:] - 1, len(reach) - 1)] - lift[at]


# --------------------------------------------------------------- the transform


def truncated_order(text: np.ndarray, depth: int) -> np.ndarray:
    """Suffixes of ``text`` (uint16, 0 ends a segment) sorted by their first ``depth`` or more characters, by doubling."""
    n = len(text)
    padded = np.concatenate([text, np.zeros(8, np.uint16)]).astype(np.uint64)
    key = np.zeros(n, np.uint64)
    for i in range(7):  # nine bits each
        key = (key << np.uint64(9)) | padded[i : i + n]
    known = 7
    while True:
        order = np.argsort(key)
        rank = np.empty(n, np.int64)
        ordered = key[order]
        rank[order] = np.cumsum(np.append(True, ordered[1:] != ordered[:-1]))
        if known >= depth or rank[order[-1]] == n:
            return order
        later = np.zeros(n, np.int64)
        later[: n - known] = rank[known:] if n > known else 0
        key = (rank.astype(np.uint64) << np.uint64(32)) | later.astype(np.uint64)
        known *= 2


def prefix_borders(text: np.ndarray, order: np.ndarray, length: int) -> np.ndarray:
    """For each place i of the sorted suffixes, whether suffixes i - 1 and i differ within ``length`` characters.

    Breadth-first backward extension: all strings of a level have one length; a
    border is set the first time an interval ends at it, so at its common-prefix
    value, and an interval whose border is already set is not extended.
    """
    n = len(text)
    bwt = text[order - 1]  # order 0 wraps around to the last terminator
    by_char = np.argsort(bwt, kind="stable")
    to = np.empty(n, np.int64)  # where the suffix one character longer stands
    to[by_char] = np.arange(n)
    same = bwt[by_char]
    before, after = np.full(n, -1, np.int64), np.full(n, n, np.int64)
    run = np.flatnonzero(same[1:] == same[:-1])
    before[by_char[run + 1]] = by_char[run]
    after[by_char[run]] = by_char[run + 1]
    border = np.zeros(n + 1, bool)
    border[[0, n]] = True
    left, right = np.array([0]), np.array([n])  # half-open intervals
    for _ in range(length):
        if not len(left):
            break
        lows, highs = [], []
        size = right - left
        cuts = np.flatnonzero(np.diff(np.append(-1, np.cumsum(size) // TEXT_CHUNK)))
        for a, b in itertools.pairwise([*cuts.tolist(), len(left)]):
            spread = size[a:b]
            base = np.cumsum(spread) - spread
            group = np.repeat(np.arange(a, b), spread)
            at = np.arange(len(group)) - np.repeat(base - left[a:b], spread)
            known = bwt[at] != 0  # no string holds a terminator
            first, last = known & (before[at] < left[group]), known & (after[at] >= right[group])
            # within an interval the extensions stand in order of character, and so do both lists once sorted
            g1, t1 = group[first], to[at[first]]
            g2, t2 = group[last], to[at[last]]
            lows.append(t1[np.lexsort((t1, g1))])
            highs.append(t2[np.lexsort((t2, g2))] + 1)
        low, high = np.concatenate(lows), np.concatenate(highs)
        fresh = ~border[high]
        low, high = low[fresh], high[fresh]
        border[high] = True
        left, right = low, high
    return border


def repeated_windows(parts: list[bytes], rank: np.ndarray, length: int) -> tuple[np.ndarray, np.ndarray]:
    """(part, offset) of each window of ``length`` bytes that also stands in an earlier part or earlier in its own.

    ``rank`` orders the parts by where they stand in the corpus: (doc, rep, first byte) as one row each.
    """
    sizes = np.array([len(p) for p in parts])
    ends = np.cumsum(sizes + 1)
    starts = ends - sizes - 1
    text = np.zeros(int(ends[-1]), np.uint16)
    body = np.ones(len(text), bool)
    body[ends - 1] = False
    text[body] = np.frombuffer(b"".join(parts), np.uint8).astype(np.uint16) + 1
    order = truncated_order(text, length)
    border = prefix_borders(text, order, length)
    group = np.cumsum(border[:-1])
    part = np.searchsorted(ends, order, side="right")
    fits = order + length < ends[part]
    group, part, off = group[fits], part[fits], (order - starts[part])[fits]
    key = np.lexsort((rank[part, 2] + off, rank[part, 1], rank[part, 0], group))
    again = key[1:][group[key[1:]] == group[key[:-1]]]
    return part[again], off[again]


# ------------------------------------------------------------------- stages


def _numbered(docs: DataFrame, id_col: str, text_col: str, carry: bool = False) -> DataFrame:
    """(doc_id, rep, body, and with ``carry`` all other columns in ``row``).

    rep tells apart different texts of one id; rows equal in both are one document.
    """
    other = [F.struct(F.col(text_col).isNull().alias("_no_text"), *[F.col(f"`{c}`").alias(f"c{i}") for i, c in enumerate(docs.columns) if c != text_col]).alias("row")] if carry else []
    rows = docs.select(F.coalesce(F.col(id_col).cast("long"), F.lit(-(1 << 63)).cast("long")).alias("doc_id"), F.col(text_col).cast("binary").alias("body"), *other)
    more = ["row"] if carry else []
    twice = common.checkpointed(rows.groupBy("doc_id").count().where("count > 1").select("doc_id"))
    if common.is_empty(twice):
        return rows.select("doc_id", F.lit(0).alias("rep"), "body", *more)
    some = common.stored(rows.join(twice, "doc_id", "left_semi").withColumn("_p", F.sha2("body", 256)), "shared-ids")
    # one row per different text of an id, numbered by ranges: an id, or none, may have any number of them
    reps = common.gapless_rank(common.stored(some.select("doc_id", "_p").distinct(), "texts"), "doc_id", "_p", "rep")
    some = some.withColumn("_q", F.coalesce("_p", F.lit(""))).join(reps.select("doc_id", F.coalesce("_p", F.lit("")).alias("_q"), (F.col("rep") + 1).cast("int").alias("rep")), ["doc_id", "_q"])
    return rows.join(twice, "doc_id", "left_anti").select("doc_id", F.lit(0).alias("rep"), "body", *more).unionByName(some.select("doc_id", "rep", "body", *more))


_ENTRY_DDL = "bucket int, data binary"


def _buckets_of(keys: np.ndarray, buckets: int) -> np.ndarray:
    return (keys % np.uint64(buckets)).astype(np.int64)


def _dealt(entry: dict[str, np.ndarray], buckets: int, blobs=None):
    """One row a bucket."""
    bucket = _buckets_of(entry["key"], buckets)
    order = np.lexsort((entry["first"], entry["rep"], entry["doc"], bucket))
    entry, bucket = _take(entry, order), bucket[order]
    cuts = np.append(np.flatnonzero(np.append(True, bucket[1:] != bucket[:-1])), len(bucket)) if len(bucket) else np.zeros(1, int)
    for a, b in itertools.pairwise(cuts.tolist()):
        yield int(bucket[a]), _take(entry, slice(a, b)), order[a:b]


def _range_batch(doc, rep, first, ends, key=None, lead=None, hot=None):
    n = len(doc)
    none = np.zeros(n, np.int64)
    return pa.RecordBatch.from_arrays(
        [pa.array(doc), pa.array(rep.astype(np.int32)), pa.array(first), pa.array(ends), pa.array(none if key is None else key.view(np.int64)), pa.array((none if lead is None else lead).astype(np.int32)), pa.array((none if hot is None else hot).astype(np.int8))],
        names=["doc_id", "rep", "first", "end", "key", "lead", "kind"],
    )


_RANGE_DDL = "doc_id long, rep int, first long, end long, key long, lead int, kind byte"  # kind 0: repeat, 1: doubtful, 2: doubtful and hot


def anchored(rows: DataFrame, length: int, anchor: int, buckets: int) -> DataFrame:
    """Entries of all segments, collapsed per map task; bucket -1 holds ranges already known to be repeats."""

    def run(batches):
        held = []

        def out():
            kept, again = _collapse(_join(held))
            held.clear()
            for bucket, some, _ in _dealt(kept, buckets):
                yield bucket, pack(some)
            doc, rep, first, ends = merge_ranges(again["doc"], again["rep"], again["first"], again["first"] + again["size"])
            for a in range(0, len(doc), 1 << 16):
                s = slice(a, a + (1 << 16))
                yield -1 - (a >> 16) % buckets, b"".join(x[s].astype("<i8").tobytes() for x in (doc, rep, first, ends))

        def sent(found):
            found = list(found)
            return pa.RecordBatch.from_arrays([pa.array([b for b, _ in found], pa.int32()), pa.array([d for _, d in found], pa.binary())], names=["bucket", "data"])

        n = 0
        for raw, doc, rep, off, ends in _pieces(batches, length):
            text, first, end, spot, h = segments(np.frombuffer(raw, np.uint8), ends, length, anchor)
            begin = np.concatenate([[0], ends[:-1]])[text]
            held.append({"key": h & _KEY_BITS, "content": _content_keys(raw, first, end), "doc": doc[text], "rep": rep[text], "first": first - begin + off[text], "size": end - first, "lead": spot - first})
            n += len(text)
            if n > FLUSH:
                yield sent(out())
                n = 0
        if held:
            yield sent(out())

    return rows.mapInArrow(run, _ENTRY_DDL)


def _by_bucket(batches):
    """Runs of equal bucket of rows sorted by it."""
    bucket, held = None, []
    for batch in batches:
        for b, data in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
            if b != bucket and held:
                yield bucket, held
                held = []
            bucket = b
            held.append(data)
    if held:
        yield bucket, held


def resolved(entries: DataFrame, hot_segments: int) -> DataFrame:
    """Ranges: repeats (all but the earliest of equal segments), and one segment of each content where an anchor has several."""

    def run(batches):
        for bucket, data in _by_bucket(batches):
            if bucket < 0:
                for raw in data:
                    doc, rep, first, ends = np.frombuffer(raw, "<i8").reshape(4, -1)
                    yield _range_batch(doc, rep, first, ends)
                continue
            kept, again = _collapse(_join([unpack(raw) for raw in data]))
            yield _range_batch(*merge_ranges(again["doc"], again["rep"], again["first"], again["first"] + again["size"]))
            key = kept["key"]
            cuts = np.flatnonzero(np.append(True, key[1:] != key[:-1]))
            size = np.diff(np.append(cuts, len(key)))
            each = np.repeat(size, size)
            some = _take(kept, each > 1)
            yield _range_batch(some["doc"], some["rep"], some["first"], some["first"] + some["size"], some["key"], some["lead"], np.where(each[each > 1] > hot_segments, 2, 1))

    return entries.repartition("bucket").sortWithinPartitions("bucket").mapInArrow(run, _RANGE_DDL)


_GATHER_DDL = "bucket int, data binary, bytes binary"


def gathered(rows: DataFrame, doubtful: DataFrame, length: int, buckets: int) -> DataFrame:
    """Entries of doubtful segments with their bytes, equal ones collapsed per map task."""
    lists = doubtful.groupBy("doc_id", "rep").agg(F.collect_list(F.struct("first", "end", "key", "lead", "kind")).alias("parts"))
    joined = rows.join(lists, ["doc_id", "rep"])

    def run(batches):
        import xxhash

        digest = xxhash.xxh3_64_intdigest
        held: dict[tuple[int, int], tuple] = {}
        again, size = [], 0

        def out():
            nonlocal held, again
            place = [(k, c, *v[:5]) for (k, c), v in held.items()]
            entry = {name: np.array([p[i] for p in place], np.uint64 if i < 2 else np.int64) for i, (name, _) in enumerate(_FIELDS)}
            blobs = [v[5] for v in held.values()]
            found = [(b, pack(e), b"".join(blobs[i] for i in rows)) for b, e, rows in _dealt(entry, buckets)]
            if again:
                packed = merge_ranges(*(np.array(x, np.int64) for x in zip(*again, strict=True)))
                found.append((-1 - len(again) % buckets, b"".join(x.astype("<i8").tobytes() for x in packed), b""))
            held, again = {}, []
            return pa.RecordBatch.from_arrays([pa.array([x[i] for x in found], kind) for i, kind in enumerate((pa.int32(), pa.binary(), pa.binary()))], names=["bucket", "data", "bytes"])

        def add(key, doc, rep, first, end, body):
            nonlocal size
            data = body[first:end]
            at = (key, digest(data) & ((1 << 48) - 1))
            mine = (doc, rep, first, end - first, 0, data)
            if (old := held.get(at)) is None:
                held[at] = mine
                size += len(data) + 64
                return
            if mine[:3] < old[:3]:
                held[at], old = mine, old
            else:
                old = mine
            if old[:3] != held[at][:3]:
                again.append((old[0], old[1], old[2], old[2] + old[3]))

        for batch in batches:
            for doc, rep, body, parts in zip(*(batch.column(i).to_pylist() for i in range(4)), strict=True):
                for p in parts:
                    first, end = p["first"], p["end"]
                    if p["kind"] == 1:
                        add(p["key"], doc, rep, first, end, body)
                        continue
                    spot = first + p["lead"]
                    lo = first
                    while lo + length <= end:  # window starts that share a core, counted from the anchor
                        hi = min(end - length, spot - ((spot - lo) // CORE_SPAN) * CORE_SPAN)
                        tail = spot - ((spot - lo) // CORE_SPAN) * CORE_SPAN
                        core = body[tail : tail - CORE_SPAN + 1 + length]
                        add(digest(core, (p["key"] ^ (spot - tail)) & ((1 << 63) - 1)) & ((1 << 48) - 1), doc, rep, lo, hi + length, body)
                        lo = hi + 1
                if size > 48 << 20:
                    yield out()
                    size = 0
        if held or again:
            yield out()

    return joined.select("doc_id", "rep", "body", "parts").mapInArrow(run, _GATHER_DDL)


def searched(parts: DataFrame, length: int) -> DataFrame:
    """Ranges of repeats among the gathered segments."""

    def run(batches):
        def grouped():
            bucket, held = None, []
            for batch in batches:
                for b, data, raw in zip(*(batch.column(i).to_pylist() for i in range(3)), strict=True):
                    if b != bucket and held:
                        yield bucket, held
                        held = []
                    bucket = b
                    held.append((data, raw))
            if held:
                yield bucket, held

        for bucket, held in grouped():
            if bucket < 0:
                for data, _ in held:
                    doc, rep, first, ends = np.frombuffer(data, "<i8").reshape(4, -1)
                    yield _range_batch(doc, rep, first, ends)
                continue
            entries = [unpack(d) for d, _ in held]
            blobs = []
            for e, (_, raw) in zip(entries, held, strict=True):
                ends = np.cumsum(e["size"])
                blobs += [raw[b - n : b] for b, n in zip(ends.tolist(), e["size"].tolist(), strict=True)]
            entry = _join(entries)
            order, new = _first_of_each(entry["key"], entry["content"], entry["doc"], entry["rep"], entry["first"])
            again = _take(entry, order[~new])
            yield _range_batch(*merge_ranges(again["doc"], again["rep"], again["first"], again["first"] + again["size"]))
            order = order[new]
            entry = _take(entry, order)
            cuts = np.flatnonzero(np.append(True, entry["key"][1:] != entry["key"][:-1]))
            counts = np.diff(np.append(cuts, len(order)))
            keep = np.flatnonzero(np.repeat(counts > 1, counts))
            entry, order = _take(entry, keep), order[keep]
            starts = np.flatnonzero(np.append(True, entry["key"][1:] != entry["key"][:-1])) if len(order) else np.zeros(0, int)
            total = np.cumsum(entry["size"] + 1)
            a = 0
            while a < len(order):  # whole anchors, about TEXT_CHUNK bytes at a time
                upto = np.searchsorted(total, (total[a - 1] if a else 0) + TEXT_CHUNK, side="right")
                cut = np.searchsorted(starts, upto, side="right") - 1
                b = len(order) if upto >= len(order) else int(starts[cut]) if starts[cut] > a else int(starts[cut + 1]) if cut + 1 < len(starts) else len(order)
                some = _take(entry, slice(a, b))
                part, off = repeated_windows([blobs[i] for i in order[a:b]], np.stack([some["doc"], some["rep"], some["first"]], axis=1), length)
                first = some["first"][part] + off
                yield _range_batch(*merge_ranges(some["doc"][part], some["rep"][part], first, first + length))
                a = b

    return parts.repartition("bucket").sortWithinPartitions("bucket").mapInArrow(run, _RANGE_DDL)


def repeated_ranges(rows: DataFrame, length: int = LENGTH, anchor: int = ANCHOR, hot_segments: int = HOT_SEGMENTS, buckets: int | None = None) -> DataFrame:
    """``(doc_id, rep, first, end)``: byte ranges of (doc_id, rep, body) rows to remove, perhaps overlapping."""
    spark = rows.sparkSession
    if not buckets:
        size = rows.agg(F.sum(F.octet_length("body"))).first()[0] or 0
        buckets = max(4 * int(spark.conf.get("spark.sql.shuffle.partitions")), -(-size // BUCKET_BYTES))
    ranges = common.stored(resolved(anchored(rows, length, anchor, buckets), hot_segments), "ranges")
    found = searched(gathered(rows, ranges.where("kind > 0"), length, buckets), length)
    return ranges.where("kind = 0").unionByName(found).select("doc_id", "rep", "first", "end")


_OUT_DDL = "n_bytes long, n_removed long, n_spans long, kept_sha256 string, kept_text string"


def _judged(docs: DataFrame, length: int, anchor: int, id_col: str, text_col: str, hot_segments: int, carry: bool) -> DataFrame:
    """(_key, n_bytes, n_removed, n_spans, kept_sha256, kept_text) per row; ``_key`` is the id, or with ``carry`` the other columns."""
    found = repeated_ranges(_numbered(docs, id_col, text_col), length, anchor, hot_segments)
    rows = _numbered(docs, id_col, text_col, carry)
    lists = found.groupBy("doc_id", "rep").agg(F.collect_list(F.struct("first", "end")).alias("parts"))
    joined = rows.join(lists, ["doc_id", "rep"], "left").select(F.col("row" if carry else "doc_id").alias("_key"), "body", "parts")
    kind = joined.schema["_key"].dataType.simpleString()

    def run(batches):
        for batch in batches:
            out = []
            for body, parts in zip(batch.column(1).to_pylist(), batch.column(2).to_pylist(), strict=True):
                body = body or b""
                if not parts:
                    out.append((len(body), 0, 0, hashlib.sha256(body).hexdigest(), body.decode("utf-8", "replace") if carry else None))
                    continue
                first = np.array([p["first"] for p in parts], np.int64)
                ends = np.array([p["end"] for p in parts], np.int64)
                zero = np.zeros(len(first), np.int64)
                _, _, first, ends = merge_ranges(zero, zero, first, ends)
                left = b"".join(body[a:b] for a, b in zip([0, *ends.tolist()], [*first.tolist(), len(body)], strict=True))
                out.append((len(body), int((ends - first).sum()), len(first), hashlib.sha256(left).hexdigest(), whole_characters(body, first, ends) if carry else None))
            kinds = (pa.int64(),) * 3 + (pa.string(),) * 2
            yield pa.RecordBatch.from_arrays([batch.column(0), *[pa.array([r[i] for r in out], k) for i, k in enumerate(kinds)]], names=["_key", "n_bytes", "n_removed", "n_spans", "kept_sha256", "kept_text"])

    return joined.mapInArrow(run, f"_key {kind}, {_OUT_DDL}")


def count_repeats(docs: DataFrame, length: int = LENGTH, anchor: int = ANCHOR, id_col: str = "doc_id", text_col: str = "text", hot_segments: int = HOT_SEGMENTS) -> DataFrame:
    """``(doc_id, n_bytes, n_removed, n_spans, kept_sha256)``, one row per input row.

    Null and shorter texts have nothing to remove. Rows equal in id and text are
    one document: each gets its result. Different texts under one id are separate
    documents, in an order that depends on their content alone; null ids come first.
    """
    out = _judged(docs, length, anchor, id_col, text_col, hot_segments, False)
    return out.select(F.nullif("_key", F.lit(-(1 << 63)).cast("long")).alias("doc_id"), "n_bytes", "n_removed", "n_spans", "kept_sha256")


def remove_repeats(docs: DataFrame, length: int = LENGTH, anchor: int = ANCHOR, id_col: str = "doc_id", text_col: str = "text", hot_segments: int = HOT_SEGMENTS, removed: str = "_n_removed") -> DataFrame:
    """``docs`` with the repeats cut out of ``text_col``, plus ``removed`` (bytes). Null texts stay null, all other columns stay.

    A character goes when all its bytes are repeats, so texts stay valid.
    """
    out = _judged(docs, length, anchor, id_col, text_col, hot_segments, True)
    place = [c for c in docs.columns]
    text = F.when(~F.col("_key._no_text"), F.col("kept_text")).alias(text_col)
    return out.select(*[text if c == text_col else F.col(f"_key.c{place.index(c)}").alias(c) for c in place], F.col("n_removed").alias(removed))


def whole_characters(body: bytes, first: np.ndarray, ends: np.ndarray) -> str:
    """The text without the characters all of whose bytes are removed."""
    data = np.frombuffer(body, np.uint8)
    gone = np.zeros(len(data) + 1, np.int64)
    np.add.at(gone, first, 1)
    np.add.at(gone, ends, -1)
    gone = np.cumsum(gone)[:-1] > 0
    heads = np.flatnonzero((data & 0xC0) != 0x80)
    out = np.repeat(np.logical_and.reduceat(gone, heads), np.diff(np.append(heads, len(data))))
    return data[~out].tobytes().decode("utf-8", "replace")
