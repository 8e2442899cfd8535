"""SentencePiece encoding and decoding (merge models) with seeded merge-dropout.

Encoding starts from characters and an agenda of neighbouring pairs that form a
piece; the best pair (highest score, then leftmost) is merged and its new
neighbours enter the agenda. With dropout, a candidate that comes up is skipped
for good where a keyed hash says so, which gives varied segmentations, all of which
decode to the same text. The hash takes the seed, the document, the position of the
word in it and the place of the merge: every occurrence draws for itself, and the same
input always gives the same pieces, on any machine.

What is remembered depends on no draw: for each word a tree of the candidates that
come up after each outcome of those before, and the pieces at its ends. Occurrences
walk the trees together, and only outcomes not met before are merged.

Pieces hold the space mark only in front (checked when a model is loaded), so
merges never reach across the start of a word and words are encoded alone.
"""

from __future__ import annotations

import heapq
import re
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, functions as F

MODEL = "/opt/tokenizers/piece_bpe_32k.model"
#: Share of candidate merges skipped, in steps of 2^-32.
DROPOUT = 0.1
#: Nodes of trees, and pieces at their ends, that a worker remembers before it starts anew.
REMEMBERED = 3_000_000

#: Words of up to so many characters are merged many at a time.
SHORT = 64
#: Characters of the texts that are encoded together (a longer text is encoded alone), and words in one call of :class:`Merger`.
TOGETHER, ROWS = 1 << 21, 1 << 14

MARK = "▁"
#: Stands for a mark that the text itself holds (no word mixes line ends with other characters).
OWN = f"\n{MARK}"
_WORDS = re.compile(f"{MARK}+[^{MARK}\n]*|[^{MARK}\n]+|\n+")


@dataclass
class Model:
    ids: dict[str, int]
    scores: dict[str, float]
    bytes_from: list[int]
    raw: list[bytes]


def load(path: str = MODEL) -> Model:
    """A merge model with byte pieces; its file is read on the driver and travels with the job (a fixed size)."""
    from sentencepiece import sentencepiece_model_pb2 as pb

    proto = pb.ModelProto()
    with open(path, "rb") as f:
        proto.ParseFromString(f.read())
    if proto.trainer_spec.model_type != pb.TrainerSpec.BPE:
        raise ValueError("not a merge model")
    normal = [(i, p.piece, p.score) for i, p in enumerate(proto.pieces) if p.type == pb.ModelProto.SentencePiece.NORMAL]
    octets = {int(p.piece[1:-1], 16): i for i, p in enumerate(proto.pieces) if p.type == pb.ModelProto.SentencePiece.BYTE}
    if len(octets) != 256 or any("\n" in p or MARK in p.lstrip(MARK) for _, p, _ in normal):
        raise ValueError("needs byte pieces, and pieces with the space mark in front only")
    raw = [b""] * len(proto.pieces)
    for i, p, _ in normal:
        raw[i] = p.replace(MARK, " ").encode()
    for b, i in octets.items():
        raw[i] = bytes([b])
    return Model({p: i for i, p, _ in normal}, {p: s for _, p, s in normal}, [octets[b] for b in range(256)], raw)


_STEP = 0x9E3779B97F4A7C15
_FULL = (1 << 64) - 1


def _mixed(x: np.ndarray) -> np.ndarray:
    x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


def keys_of(seed: int, doc: int, n: int) -> np.ndarray:
    """The key of each of the first ``n`` words of a document."""
    start = np.uint64((seed * _STEP + (doc & _FULL) * 0xD1B54A32D192ED03) & _FULL)
    return _mixed(_mixed(np.arange(n, dtype=np.uint64) * np.uint64(0xA0761D6478BD642F) + start))


def places(a: np.ndarray, middle: np.ndarray, end: np.ndarray) -> np.ndarray:
    """One number for the merge of word[a:middle] and word[middle:end]."""
    return ((a.astype(np.uint64) << np.uint64(42)) | (middle.astype(np.uint64) << np.uint64(21)) | end.astype(np.uint64)) * np.uint64(_STEP)


def dropped(keys: np.ndarray, at: np.ndarray, limit: int) -> np.ndarray:
    """Whether words of these keys drop the merges at these places: 32 bits of a hash against ``limit``."""
    return (_mixed(keys + at) >> np.uint64(32)) < np.uint64(limit)


def encode_word(word: str, model: Model, key: int = 0, limit: int = 0) -> list[int]:
    """Pieces of one word, by the queue."""
    out, ids = [], model.ids
    for piece in _queued(word, model.scores, key, limit):
        found = ids.get(piece)
        if found is None:
            out += [model.bytes_from[b] for b in piece.encode()]
        else:
            out.append(found)
    return out


class Merger:
    """The same agenda for many words of one length at once, in numpy.

    A part is a number: the id of its piece, or ``base`` plus the code point of a
    character that is none. Each word has a row; a part stands in the column of its
    first character and knows the columns of its neighbours, the last column being
    none. The agenda holds, at a part's column, the rank of the merge with its right
    neighbour, or -1; each step takes the first of the best in every row.
    """

    def __init__(self, model: Model):
        self.base = len(model.raw)
        self.width = self.base + 0x110000
        self.part_of = np.arange(0x110000, dtype=np.int64) + self.base
        for piece, i in model.ids.items():
            if len(piece) == 1:
                self.part_of[ord(piece)] = i
        rank = {s: r for r, s in enumerate(sorted(set(model.scores.values())))}
        merges = {}
        for piece, i in model.ids.items():
            for k in range(1, len(piece)):
                left, right = self._part(piece[:k], model), self._part(piece[k:], model)
                if left is not None and right is not None:
                    merges[left * self.width + right] = (i, rank[model.scores[piece]])
        self.octets = np.array(model.bytes_from, np.int64)
        self._table(merges)

    def _part(self, piece: str, model: Model) -> int | None:
        return model.ids.get(piece, self.base + ord(piece) if len(piece) == 1 else None)

    def _slots(self, keys: np.ndarray) -> np.ndarray:
        return ((keys.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15)) >> self.shift).astype(np.int64)

    def _table(self, merges: dict[int, tuple[int, int]]) -> None:
        """Merges in an open hash table, an eighth full at most."""
        bits = max(4, (8 * len(merges)).bit_length())
        self.shift, self.mask = np.uint64(64 - bits), (1 << bits) - 1
        self.keys, self.into, self.rank = np.full(1 << bits, -1, np.int64), np.full(1 << bits, -1, np.int64), np.full(1 << bits, -1, np.int32)
        for key, slot in zip(merges, self._slots(np.array(list(merges), np.int64)).tolist(), strict=True):
            while self.keys[slot] >= 0:
                slot = (slot + 1) & self.mask
            self.keys[slot], (self.into[slot], self.rank[slot]) = key, merges[key]

    def find(self, left: np.ndarray, right: np.ndarray) -> np.ndarray:
        """Slots of the merges of parts; where there is no such merge, an empty slot."""
        keys = left * self.width + right
        slots = self._slots(keys)
        held = self.keys[slots]
        open_ = np.flatnonzero((held != keys) & (held >= 0))
        while len(open_):
            slots[open_] = (slots[open_] + 1) & self.mask
            held = self.keys[slots[open_]]
            open_ = open_[(held != keys[open_]) & (held >= 0)]
        return slots

    def encode(self, words: list[str], keys: np.ndarray, limit: int) -> tuple[np.ndarray, np.ndarray, list[tuple[np.ndarray, np.ndarray, np.ndarray]]]:
        """Words of one length: their piece ids in a row, how many each has, and for each step the words that took it, the places and what was dropped."""
        n, length = len(words), len(words[0])
        steps = []
        wide = length + 1
        parts = np.empty((n, wide), np.int64)
        parts[:, :length] = self.part_of[np.frombuffer("".join(words).encode("utf-32-le"), np.uint32).reshape(n, length)]
        parts[:, length] = self.width - 1  # no character: the end, and what stands before the start
        before, after = np.empty((n, wide), np.int64), np.empty((n, wide), np.int64)
        before[:], after[:] = np.arange(-1, length), np.arange(1, wide + 1)
        before[:, 0] = length
        slots = np.full((n, wide), -1, np.int64)
        slots[:, :length] = self.find(parts[:, :length].ravel(), parts[:, 1:].ravel()).reshape(n, length)
        agenda = self.rank[slots]
        agenda[:, length] = -1
        parts, before, after, slots, todo = parts.ravel(), before.ravel(), after.ravel(), slots.ravel(), np.arange(n)
        flat = agenda.ravel()
        while len(todo):
            at = (agenda if len(todo) == n else agenda[todo]).argmax(1)
            left = todo * wide + at
            live = flat[left] >= 0
            todo, at, left = todo[live], at[live], left[live]
            start = todo * wide
            middle = after[left]
            end = after[start + middle]
            if limit:
                place = places(at, middle, end)
                drop = dropped(keys[todo], place, limit)
                steps.append((todo, place, drop))
                flat[left[drop]] = -1
                keep = ~drop
                at, left, start, middle, end = at[keep], left[keep], start[keep], middle[keep], end[keep]
            parts[left] = self.into[slots[left]]
            gone = start + middle
            parts[gone], flat[gone] = -1, -1
            after[left] = end
            before[start + end] = at
            for a, b in ((start + before[left], left), (left, start + end)):
                slots[a] = found = self.find(parts[a], parts[b])
                flat[a] = self.rank[found]
        parts = parts.reshape(n, wide)[:, :length]
        stays = parts >= 0
        found = parts[stays]
        sizes = np.ones(len(found), np.int64)
        unknown = found >= self.base
        if unknown.any():
            points = found[unknown] - self.base
            sizes[unknown] = 1 + (points > 0x7F) + (points > 0x7FF) + (points > 0xFFFF)
            found, raw = np.repeat(found, sizes), np.frombuffer(points.astype("<u4").tobytes().decode("utf-32-le").encode(), np.uint8)
            found[np.repeat(unknown, sizes)] = self.octets[raw]
        each = np.zeros((n, length), np.int64)
        each[stays] = sizes
        return found.astype(np.int32), each.sum(1), steps


def _queued(word: str, scores: dict[str, float], key: int, limit: int) -> list[str]:
    """The agenda of one word as a priority queue: for long words, and the measure of :class:`Merger`."""
    n = len(word)
    ends, before, after = list(range(1, n + 1)), list(range(-1, n - 1)), list(range(1, n + 1))
    agenda = []

    def propose(a):
        b = after[a]
        if b < n and (s := scores.get(word[a : ends[b]])) is not None:
            heapq.heappush(agenda, (-s, a, ends[a], ends[b]))

    for a in range(n - 1):
        propose(a)
    gone = [False] * n
    while agenda:
        _, a, middle, end = heapq.heappop(agenda)
        if gone[a] or ends[a] != middle or middle >= n or gone[middle] or ends[middle] != end:
            continue  # a part has been merged meanwhile
        if limit and _drops(key, a, middle, end, limit):
            continue
        gone[middle] = True
        ends[a] = end
        after[a] = after[middle]
        if after[a] < n:
            before[after[a]] = a
        if before[a] >= 0:
            propose(before[a])
        propose(a)
    out, a = [], 0
    while a < n:
        out.append(word[a : ends[a]])
        a = ends[a]
    return out


def _drops(key: int, a: int, middle: int, end: int, limit: int) -> bool:
    x = (key + ((a << 42) | (middle << 21) | end) * _STEP) & _FULL
    x = ((x ^ (x >> 30)) * 0xBF58476D1CE4E5B9) & _FULL
    x = ((x ^ (x >> 27)) * 0x94D049BB133111EB) & _FULL
    return ((x ^ (x >> 31)) >> 32) < limit


class _Grown:
    """An array that grows at its end."""

    def __init__(self, kind):
        self.all, self.n = np.zeros(1 << 12, kind), 0

    def add(self, values: np.ndarray) -> int:
        """Where the values now start."""
        start, self.n = self.n, self.n + len(values)
        if self.n > len(self.all):
            self.all = np.concatenate([self.all, np.zeros(max(self.n, len(self.all)), self.all.dtype)])
        self.all[start : self.n] = values
        return start


class Coder:
    """Encodes with one seed and dropout.

    A node of a word's tree is a candidate merge: ``place`` says which, and ``next[2 *
    node + dropped]`` what comes then: a node, -1 where that was not met yet, or -2 - i for
    the pieces number i. A word's entry is a node without a place, of which only the first
    is used. Words of over SHORT characters are encoded alone and not remembered.
    """

    def __init__(self, model: Model, dropout: float = DROPOUT, seed: int = 1):
        self.model, self.limit, self.seed = model, round(dropout * (1 << 32)), seed
        self.merger = Merger(model)
        self.own_mark = np.array([model.bytes_from[b] for b in MARK.encode()], np.int32)
        self._anew()

    def _anew(self) -> None:
        self.entry: dict[str, int] = {}
        self.words: list[str] = []
        self.place, self.next = _Grown(np.uint64), _Grown(np.int32)
        self.pieces, self.starts, self.sizes = _Grown(np.int32), _Grown(np.int64), _Grown(np.int64)
        self._ends(self.own_mark, np.array([len(self.own_mark)]))
        self.entry[OWN] = self._nodes(np.zeros(1, np.uint64))
        self.next.all[0] = -2

    def _nodes(self, place: np.ndarray) -> int:
        self.next.add(np.full(2 * len(place), -1, np.int32))
        return self.place.add(place)

    def _ends(self, pieces: np.ndarray, sizes: np.ndarray) -> int:
        start = self.pieces.add(pieces)
        self.starts.add(start + np.cumsum(sizes) - sizes)
        return self.sizes.add(sizes)

    def _grow(self, words: list[str], keys: np.ndarray, edges: np.ndarray, depths: np.ndarray) -> None:
        """Merge words of one length, each of which came to an edge (2 * node + dropped) that was not met yet, after so many draws; edges differ."""
        pieces, sizes, steps = self.merger.encode(words, keys, self.limit)
        end = self._ends(pieces, sizes) + np.arange(len(words))
        came = edges.copy()  # the edge at which each word's path ends so far
        for depth, (todo, place, drop) in enumerate(steps):
            new = depths[todo] <= depth
            todo, place, drop = todo[new], place[new], drop[new]
            if len(todo):
                node = self._nodes(place) + np.arange(len(todo))
                self.next.all[came[todo]] = node
                came[todo] = 2 * node + drop
        self.next.all[came] = -2 - end

    def _walk(self, words: list[str], entries: np.ndarray, keys: np.ndarray) -> np.ndarray:
        """The number of the pieces of each word."""
        at, edge, depth = self.next.all[2 * entries], 2 * entries, np.zeros(len(entries), np.int64)
        lengths = None
        while True:
            on = np.flatnonzero(at >= 0)
            while len(on):
                node = at[on]
                drop = dropped(keys[on], self.place.all[node], self.limit)
                edge[on] = 2 * node.astype(np.int64) + drop
                depth[on] += 1
                at[on] = self.next.all[edge[on]]
                on = on[at[on] >= 0]
            open_ = np.flatnonzero(at == -1)
            if not len(open_):
                return -2 - at
            edges, first = np.unique(edge[open_], return_index=True)
            some = open_[first]
            lengths = np.fromiter(map(len, words), np.int64, len(words)) if lengths is None else lengths
            order = np.argsort(lengths[some], kind="stable")
            some, edges = some[order], edges[order]
            for same in np.split(np.arange(len(some)), np.flatnonzero(np.diff(lengths[some])) + 1):
                for k in range(0, len(same), ROWS):
                    few = some[same[k : k + ROWS]]
                    self._grow([words[i] for i in few.tolist()], keys[few], edges[same[k : k + ROWS]], depth[few])
            at[open_] = self.next.all[edge[open_]]

    def _words(self, text: str) -> list[str]:
        """Words of a text. A text's own marks part it and go to bytes."""
        if MARK not in text:
            return _WORDS.findall(MARK + text.replace(" ", MARK))
        words = []
        for i, part in enumerate(text.split(MARK)):
            words += [OWN, *_WORDS.findall(part.replace(" ", MARK))] if i else _WORDS.findall(MARK + part.replace(" ", MARK))
        return words

    def encode_all(self, texts: list[str], docs: list[int]) -> list[np.ndarray]:
        """Piece ids of each text; its number in ``docs`` is part of all draws."""
        if max(self.place.n, self.starts.n, self.pieces.n >> 2) >= REMEMBERED:
            self._anew()
        held = [self._words(t) if t else [] for t in texts]
        words = [w for some in held for w in some]
        counts = np.array([len(some) for some in held], np.int64)
        keys = np.concatenate([keys_of(self.seed, d, n) for d, n in zip(docs, counts.tolist(), strict=True)]) if self.limit else np.zeros(len(words), np.uint64)
        entry = self.entry
        found = [entry.get(w, -1) for w in words]
        long = []
        if -1 in found:
            new = list(dict.fromkeys(w for w, e in zip(words, found, strict=True) if e < 0 and (len(w) <= SHORT or w == OWN)))
            first = self._nodes(np.zeros(len(new), np.uint64))
            entry.update(zip(new, range(first, first + len(new)), strict=True))
            found = [entry.get(w, -1) for w in words]
            long = [i for i, e in enumerate(found) if e < 0]
        entries = np.array(found, np.int64)
        entries[long] = entry[OWN]
        end = self._walk(words, entries, keys)
        for i in long:
            ids = np.array(encode_word(words[i], self.model, int(keys[i]), self.limit), np.int32)
            end[i] = self._ends(ids, np.array([len(ids)]))
        sizes, starts = self.sizes.all[end], self.starts.all[end]
        upto = np.cumsum(sizes)
        flat = self.pieces.all[np.repeat(starts - (upto - sizes), sizes) + np.arange(upto[-1] if len(upto) else 0)]
        cuts = np.append(0, upto)[np.append(0, np.cumsum(counts))]
        return [flat[a:b] for a, b in zip(cuts[:-1].tolist(), cuts[1:].tolist(), strict=True)]

    def encode(self, text: str, doc: int = 0) -> np.ndarray:
        """Piece ids of one text."""
        return self.encode_all([text], [doc])[0]


def together(texts: list[str | None], most: int = TOGETHER) -> list[tuple[int, int]]:
    """Runs of texts that hold ``most`` characters at most, or one text."""
    cuts, size = [0], 0
    for i, t in enumerate(texts):
        size += len(t or "")
        if size > most and i > cuts[-1]:
            cuts.append(i)
            size = len(t or "")
    return list(zip(cuts, [*cuts[1:], len(texts)], strict=True))


def decode(ids, model: Model) -> str:
    """The text of piece ids, whatever segmentation they are."""
    return b"".join(map(model.raw.__getitem__, ids))[1:].decode("utf-8", "replace")


_coders: dict[tuple, Coder] = {}


def encode(docs: DataFrame, model_path: str = MODEL, dropout: float = DROPOUT, seed: int = 1, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``(doc_id, n_tokens, ids, lossless)``: piece ids, and whether they decode to the text, one row per input row.

    A null text has null ids, an empty one none. Null ids (of documents) count as 0 in the
    hash, and repeated rows of one id draw alike.
    """
    model = docs.sparkSession.sparkContext.broadcast(load(model_path))  # one vocabulary, a fixed size

    def run(batches):
        key = (model_path, dropout, seed)
        coder = _coders.get(key) or _coders.setdefault(key, Coder(model.value, dropout, seed))
        for batch in batches:
            numbers, texts = [d or 0 for d in batch.column(0).to_pylist()], batch.column(1).to_pylist()
            found = [x for a, b in together(texts) for x in coder.encode_all([t or "" for t in texts[a:b]], numbers[a:b])]
            found = [None if t is None else x for t, x in zip(texts, found, strict=True)]
            same = [t is None or decode(x.tolist(), coder.model) == t for t, x in zip(texts, found, strict=True)]
            lengths = [0 if x is None else len(x) for x in found]
            flat = np.concatenate([x for x in found if x is not None] or [np.zeros(0, np.int32)])
            offsets = pa.array([None if x is None else o for x, o in zip(found, np.cumsum([0, *lengths])[:-1].tolist(), strict=True)] + [len(flat)], pa.int32())
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(lengths, pa.int64()), pa.ListArray.from_arrays(offsets, pa.array(flat)), pa.array(same)], names=["doc_id", "n_tokens", "ids", "lossless"])

    return docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text")).mapInArrow(run, "doc_id long, n_tokens long, ids array<int>, lossless boolean")


def decode_rows(rows: DataFrame, model_path: str = MODEL, id_col: str = "doc_id", ids_col: str = "ids") -> DataFrame:
    """``(doc_id, text)`` of rows of piece ids; null ids give a null text."""
    model = rows.sparkSession.sparkContext.broadcast(load(model_path))

    def run(batches):
        for batch in batches:
            texts = [None if ids is None else decode(ids, model.value) for ids in batch.column(1).to_pylist()]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(texts, pa.string())], names=["doc_id", "text"])

    return rows.select(F.col(id_col).cast("long").alias("doc_id"), F.col(ids_col).alias("ids")).mapInArrow(run, "doc_id long, text string")
