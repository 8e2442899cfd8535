"""Length buckets of least padding, and token-budget batches inside each.

Every text is padded to the upper bound of its bucket. Where the bounds stand is
chosen by dynamic programming over the histogram of lengths of all rows: the cost
of a bucket from one length to another is the padding of all rows in it, and the
cheapest division into k buckets extends the cheapest division into k - 1 of a
shorter range. The best cut moves right as the range grows, so each layer is
solved by divide and conquer, one numpy step per level.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column, DataFrame, functions as F

from netprop.llm import common

BUCKETS = 16
TOKEN_BUDGET = 16384
#: Lengths are rounded up to a multiple of this before they are counted, as accelerators want them.
MULTIPLE = 8


def token_count(text: Column) -> Column:
    """Words, as parted by 0x20 and 0x09-0x0D; a null or blank text has none."""
    words = F.size(F.filter(F.split(text, "[\\x20\\x09-\\x0D]+"), lambda w: w != ""))
    return F.when(text.isNull(), F.lit(0)).otherwise(words).cast("long")


def best_bounds(lengths: np.ndarray, counts: np.ndarray, buckets: int) -> tuple[list[int], int]:
    """Upper bounds (each an occurring length) of at most ``buckets`` buckets, and the padding they leave in all."""
    lengths, counts = np.asarray(lengths, np.int64), np.asarray(counts, np.int64)
    n = len(lengths)
    if not n:
        return [], 0
    rows = np.concatenate([[0], np.cumsum(counts)]).astype(np.float64)
    mass = np.concatenate([[0], np.cumsum(counts * lengths)]).astype(np.float64)

    def cost(i, j):  # lengths i .. j - 1 in one bucket
        return lengths[j - 1] * (rows[j] - rows[i]) - (mass[j] - mass[i])

    best = np.full(n + 1, np.inf)
    best[0] = 0.0
    cuts = []
    for _ in range(min(buckets, n)):
        new, cut = np.full(n + 1, np.inf), np.zeros(n + 1, np.int64)
        new[0] = 0.0
        spans = [(1, n, 0, n - 1)]
        while spans:
            lo, hi, a, b = map(np.array, zip(*spans, strict=True))
            mid = (lo + hi) // 2
            last = np.minimum(b, mid - 1)
            size = np.maximum(last - a + 1, 1)
            at = np.repeat(np.arange(len(mid)), size)
            i = np.arange(len(at)) - np.repeat(np.cumsum(size) - size, size) + a[at]
            value = best[i] + cost(i, mid[at])
            starts = np.cumsum(size) - size
            least = np.minimum.reduceat(value, starts)
            hit = np.flatnonzero(value == least[at])
            first = hit[np.unique(at[hit], return_index=True)[1]]
            new[mid], cut[mid] = least, i[first]
            spans = [s for k in range(len(mid)) for s in ((lo[k], mid[k] - 1, a[k], i[first[k]]), (mid[k] + 1, hi[k], i[first[k]], b[k])) if s[0] <= s[1]]
        cuts.append(cut)
        best = new
    bounds, j = [], n
    for cut in reversed(cuts):
        if j == 0:
            break
        bounds.append(int(lengths[j - 1]))
        j = int(cut[j])
    return bounds[::-1], int(round(best[n]))


def histogram(rows: DataFrame, multiple: int = MULTIPLE) -> tuple[np.ndarray, np.ndarray]:
    """Occurring padded lengths and their counts over all rows: as many rows as there are lengths."""
    got = rows.groupBy(padded(F.col("n_tokens"), multiple).alias("length")).count().toPandas().sort_values("length")
    return got["length"].to_numpy(np.int64), got["count"].to_numpy(np.int64)


def padded(n: Column, multiple: int) -> Column:
    return (F.ceil(n / multiple) * multiple).cast("long")


def bucket_column(length: Column, bounds: list[int]) -> Column:
    """Number of the bucket: how many bounds are smaller."""
    steps = F.array(*[F.lit(b).cast("long") for b in bounds])
    return F.size(F.filter(steps, lambda b: b < length)).cast("int")


def pack(docs: DataFrame, buckets: int = BUCKETS, budget: int = TOKEN_BUDGET, multiple: int = MULTIPLE, id_col: str = "doc_id", text_col: str = "text", length_col: str | None = None) -> DataFrame:
    """``(doc_id, n_tokens, bucket, padded_tokens, batch, place)``, one row per input row.

    ``batch`` numbers the batches of a bucket and ``place`` the rows of a batch,
    both from 0. A batch of padded rows keeps to ``budget`` tokens; a row longer
    than that is a batch of its own, uncut. Null and blank texts have no tokens
    and share bucket 0. Equal ids are told apart by length and checksum.

    Tokens are words, unless ``length_col`` holds their number (say, of pieces). Padding is
    least among bounds that are multiples of ``multiple`` (1: among all).
    """
    body = F.col(text_col)
    length = F.coalesce(F.col(length_col).cast("long"), F.lit(0)) if length_col else token_count(body)
    rows = docs.select(F.col(id_col).cast("long").alias("doc_id"), length.alias("n_tokens"), F.coalesce(F.crc32(body.cast("binary")), F.lit(0)).alias("_crc"))
    rows = common.stored(rows, "lengths")
    lengths, counts = histogram(rows, multiple)
    bounds, _ = best_bounds(lengths, counts, buckets)
    bounds = bounds or [0]
    placed = rows.withColumn("bucket", bucket_column(padded(F.col("n_tokens"), multiple), bounds))
    bound = F.element_at(F.array(*[F.lit(b).cast("long") for b in bounds]), F.col("bucket") + 1)
    ranked = common.gapless_rank(placed, "bucket", "doc_id", "_slot", ("n_tokens", "_crc")).withColumn("padded_tokens", bound)
    room = F.greatest(F.lit(1).cast("long"), F.floor(F.lit(budget) / F.greatest(F.col("padded_tokens"), F.lit(1))).cast("long"))
    return ranked.select("doc_id", "n_tokens", "bucket", "padded_tokens", F.floor(F.col("_slot") / room).cast("long").alias("batch"), (F.col("_slot") % room).cast("long").alias("place"))
