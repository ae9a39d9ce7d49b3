"""Best-fit packing of token sequences, improved by a swap-based local search.

``token_pieces`` cuts tokenised documents into pieces of at most ``capacity`` tokens, ``pack``
puts the pieces into sequences.  Packing runs in groups of pieces chosen by a hash, so no task
holds more than a few thousand of them whatever the size of the corpus; a second pass packs the
sequences that the groups left underfull once more, across groups.  Both start from best fit in an
order that has nothing to do with lengths, which the search improves.

Defined results: a null text is an empty document (one piece, the end id alone); repeated rows
are packed each on their own; a null doc_id is kept; an empty table gives no pieces; other
columns of the input are ignored.
"""

from __future__ import annotations

import functools
import os
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from bitsort.llm.stages import removed, written
from bitsort.llm.text import CACHES

CAPACITY = 2048
PIECES = "doc_id long, piece int, start long, length long, ids_crc32 long"
PACKED = PIECES + ", sequence_id long, offset long"
#: Documents whose pieces are packed together in the first pass, and groups joined in the second.
GROUP_DOCS, FAN_IN = 4096, 64
#: Words that a worker keeps with their ids before it starts anew, and bytes of text split at once.
CACHE_WORDS, SLICE_BYTES = 1_700_000, 6 << 20
#: The local search ends with a round of so many sequences, emptiest first, from which no step leads.
PATIENCE = 16
_PLAIN, _MARKS = frozenset(b"abcdefghijklmnopqrstuvwxyz0123456789"), b".,;:!?&$#%*"


class WordTokenizer:
    """ids of texts, word by word.

    Valid for tokenizers whose rules never look across ASCII white space, ignore case and part
    letters and digits from punctuation (as word_bpe_49k): the ids of a text are those of its
    words, and each distinct word is encoded once, without its final marks.  Words are numbered;
    ``ids[first[k] : first[k] + count[k]]`` are those of word k.  Word 0 is empty.
    """

    def __init__(self, path: str):
        os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")
        from tokenizers import Tokenizer

        self.tokenizer = Tokenizer.from_file(path)
        vocabulary = self.tokenizer.get_vocab()
        self.ends = np.zeros(max(vocabulary.values()) + 1, dtype=bool)  # tokens that end a unit
        self.ends[[i for t, i in vocabulary.items() if t.endswith("</w>")]] = True
        self.clear()

    def clear(self) -> None:
        self.known: dict[bytes, int] = {b"": 0}
        self.used = 0
        self.ids = np.zeros(1 << 16, dtype="<u4")
        self.first = np.zeros(1 << 12, dtype=np.int64)
        self.count = np.zeros(1 << 12, dtype=np.int64)

    def _numbered(self, words: list[bytes], lengths: np.ndarray, ids: np.ndarray) -> None:
        """Number unknown ``words``; their ids lie back to back in ``ids``."""
        n, k = len(self.known), len(words)
        while n + k > len(self.first):
            self.first, self.count = np.concatenate([self.first, self.first]), np.concatenate([self.count, self.count])
        while self.used + len(ids) > len(self.ids):
            self.ids = np.concatenate([self.ids, self.ids])
        self.first[n : n + k] = self.used + np.cumsum(lengths) - lengths
        self.count[n : n + k] = lengths
        self.ids[self.used : self.used + len(ids)] = ids
        self.used += len(ids)
        self.known.update(zip(words, range(n, n + k), strict=True))

    def _encode_plain(self, words: list[bytes]) -> list[bytes]:
        """Number words of letters, one unit each, many in one call; the words of lines that do not fit that are handed back."""
        lines = [words[i : i + 256] for i in range(0, len(words), 256)]
        found = [np.array(e.ids, dtype="<u4") for e in self.tokenizer.encode_batch_fast([b" ".join(x).decode("utf-8", "replace") for x in lines], add_special_tokens=False)]
        bad = []
        for line, ids in zip(lines, found, strict=True):
            cut = np.flatnonzero(self.ends[ids]) + 1
            if len(cut) == len(line) and cut[-1] == len(ids):
                self._numbered(line, np.diff(cut, prepend=0), ids)
            else:
                bad += line
        return bad

    def _encode_each(self, words: list[bytes]) -> None:
        found = [e.ids for e in self.tokenizer.encode_batch_fast([w.decode("utf-8", "replace") for w in words], add_special_tokens=False)]
        self._numbered(words, np.array([len(x) for x in found], dtype=np.int64), np.fromiter((i for x in found for i in x), "<u4"))

    def learn(self, words: list[bytes]) -> None:
        """Number distinct unknown ``words`` and their stems."""
        marked, stems, known = [], set(), self.known
        for w in words:
            stem = w.rstrip(_MARKS)
            if len(stem) < len(w) and stem and stem[-1] in _PLAIN:  # only after an ASCII letter or digit do marks stand apart
                marked.append((w, stem, w[len(stem) :]))
                stems.update((stem, w[len(stem) :]))
            else:
                stems.add(w)
        new = [x for x in stems if x not in known]
        plain = [x for x in new if x.isalpha() or (not x.isascii() and x.decode("utf-8", "replace").isalpha())]
        odd = set(plain)
        rest = [x for x in new if x not in odd] + (self._encode_plain(plain) if plain else [])
        if rest:
            self._encode_each(rest)
        marked = [m for m in marked if m[0] not in known]
        if marked:
            both = np.array([(known[s], known[m]) for _, s, m in marked], dtype=np.int64).ravel()
            self._numbered([w for w, _, _ in marked], self.count[both].reshape(-1, 2).sum(axis=1), self._gathered(both))

    def _gathered(self, numbers: np.ndarray) -> np.ndarray:
        """The ids of numbered words, back to back."""
        count = self.count[numbers]
        ends = np.cumsum(count)
        return self.ids[np.repeat(self.first[numbers] - ends + count, count) + np.arange(int(ends[-1]) if len(ends) else 0)]

    def encode(self, texts: pa.Array, end_id: int) -> tuple[np.ndarray, np.ndarray]:
        """(ids of all texts, each followed by ``end_id``; where each text's ids end)."""
        if len(self.known) > CACHE_WORDS:
            self.clear()
        # case does not matter, but for the tokenizer's special tokens, which it looks for as written
        lists = pc.ascii_split_whitespace(pc.if_else(pc.match_substring(texts, "<|"), texts, pc.ascii_lower(texts)))
        edges = lists.offsets.to_numpy().astype(np.int64)
        found = lists.flatten().cast(pa.binary()).dictionary_encode()
        words = found.dictionary.to_pylist()
        number = list(map(self.known.get, words))
        if None in number:
            self.learn([w for w, n in zip(words, number, strict=True) if n is None])
            number = map(self.known.__getitem__, words)
        number = np.fromiter(number, np.int64, len(words))[found.indices.to_numpy()]
        total = np.concatenate([[0], np.cumsum(self.count[number])])
        ends = total[edges[1:] - edges[0]] + np.arange(1, len(texts) + 1)
        out = np.empty(int(total[-1]) + len(texts), dtype="<u4")
        is_end = np.zeros(len(out), dtype=bool)
        is_end[ends - 1] = True
        out[is_end] = end_id
        out[~is_end] = self._gathered(number)
        return out, ends


@functools.lru_cache(maxsize=2)
def tokenizer_at(path: str) -> WordTokenizer:
    """One tokenizer, with its known words, for all tasks that a worker process runs."""
    return WordTokenizer(path)


CACHES.append(tokenizer_at.cache_clear)


def _slices(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """The rows in runs of about SLICE_BYTES of text; a longer text is taken as a whole."""
    held, size = [], 0
    for batch in batches:
        held.append(batch)
        size += batch.column(1).nbytes
        if size >= SLICE_BYTES:
            yield pa.Table.from_batches(held).combine_chunks().to_batches()[0]
            held, size = [], 0
    if held and sum(b.num_rows for b in held):
        yield pa.Table.from_batches(held).combine_chunks().to_batches()[0]


def token_pieces(docs: DataFrame, tokenizer_path: str, capacity: int = CAPACITY, end_id: int = 0) -> DataFrame:
    """Rows (doc_id, piece, start, length, ids_crc32): every document's ids, then ``end_id``, cut at ``capacity``."""

    def cut(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        tokenizer = tokenizer_at(tokenizer_path)
        for batch in _slices(batches):
            ids, ends = tokenizer.encode(batch.column(1).fill_null(""), end_id)
            sizes = np.diff(ends, prepend=0)
            pieces = -(-sizes // capacity)
            doc = np.repeat(np.arange(len(sizes)), pieces)
            piece = np.arange(len(doc)) - np.repeat(np.cumsum(pieces) - pieces, pieces)
            start = piece * capacity
            length = np.minimum(sizes[doc] - start, capacity)
            at = (ends - sizes)[doc] + start
            data = memoryview(ids).cast("B")
            crc = [zlib.crc32(data[4 * i : 4 * j]) for i, j in zip(at.tolist(), (at + length).tolist(), strict=True)]
            yield pa.RecordBatch.from_arrays(
                [batch.column(0).take(pa.array(doc)), pa.array(piece, pa.int32()), pa.array(start, pa.int64()), pa.array(length, pa.int64()), pa.array(crc, pa.int64())],
                ["doc_id", "piece", "start", "length", "ids_crc32"],
            )

    return docs.select(F.col("doc_id").cast("long"), F.col("text").cast("string")).mapInArrow(cut, PIECES)


class _Bins:
    """Open sequences, found by the free space they have."""

    def __init__(self, capacity: int):
        self.capacity, self.items, self.fill = capacity, [], []
        self.by_gap: list[list[int]] = [[] for _ in range(capacity + 1)]
        self.mask = 0  # bit g: some bin has exactly g tokens free

    def _note(self, b: int) -> None:
        gap = self.capacity - self.fill[b]
        self.by_gap[gap].append(b)
        self.mask |= 1 << gap

    def best_fit(self, length: int) -> int:
        """The bin with the least free space that still takes ``length``; a new one if there is none."""
        rest = self.mask >> length
        if rest:
            gap = length + (rest & -rest).bit_length() - 1
            b = self.by_gap[gap].pop()
            if not self.by_gap[gap]:
                self.mask &= ~(1 << gap)
            return b
        self.items.append([])
        self.fill.append(0)
        return len(self.items) - 1

    def put(self, item: int, length: int) -> None:
        b = self.best_fit(length)
        self.items[b].append(item)
        self.fill[b] += length
        self._note(b)


def best_fit(lengths: np.ndarray, capacity: int, order: np.ndarray | None = None) -> np.ndarray:
    """The sequence of each piece when pieces come in ``order`` (as they lie by default)."""
    bins = _Bins(capacity)
    for i in (range(len(lengths)) if order is None else order.tolist()):
        bins.put(i, int(lengths[i]))
    out = np.empty(len(lengths), dtype=np.int64)
    for b, items in enumerate(bins.items):
        out[items] = b
    return out


def best_fit_decreasing(lengths: np.ndarray, capacity: int) -> np.ndarray:
    """Longest pieces first: what the local search is compared with."""
    return best_fit(lengths, capacity, np.argsort(-lengths, kind="stable"))


def local_search(lengths: np.ndarray, place: np.ndarray, capacity: int, patience: int = PATIENCE) -> np.ndarray:
    """Empty underfull sequences by moving and exchanging pieces.

    The sequence with the least fill gives: a piece moves over, one piece is exchanged for a
    smaller one, two for one smaller than both together, or one for two smaller ones.  Each step
    shifts tokens from a sequence to one at least as full, so the sum of squared fills grows and
    the search ends: at the lower bound, ceil(sum / capacity), or with a round of ``patience``
    sequences from which no step leads.  Pieces of one length in one sequence are alike,
    and at most 63 lengths fit 2048 tokens, so all exchanges are tried.
    """
    place, n_bins = place.copy(), int(place.max()) + 1 if len(place) else 0
    fill = np.bincount(place, weights=lengths, minlength=n_bins).astype(np.int64)
    alive = int((fill > 0).sum())
    least = -(-int(lengths.sum()) // capacity)
    stuck = np.zeros(n_bins, dtype=bool)
    tries, moves = patience, 0
    while alive > least:
        open_bins = np.flatnonzero((fill > 0) & (fill < capacity))
        sources = open_bins[~stuck[open_bins]]
        if not len(sources) or tries == 0:
            if not moves:
                break
            stuck[:] = False  # steps since the last such round may have made room for earlier ones
            tries, moves = patience, 0
            continue
        s = int(sources[np.argmin(fill[sources])])
        move = _best_step(lengths, place, fill, capacity, s)
        if move is None:
            stuck[s] = True
            tries -= 1
            continue
        moves += 1
        give, take, target = move
        moved = int(lengths[give].sum() - lengths[take].sum())
        place[give], place[take] = target, s
        fill[target] += moved
        fill[s] -= moved
        stuck[target] = False
        if fill[s] == 0:
            alive -= 1
            tries = patience
    return place


def _best_step(lengths, place, fill, capacity, s):
    """(pieces to give, pieces to take, target) that shifts the most tokens out of ``s``, or None."""
    mine = np.flatnonzero(place == s)
    sizes, first, count = np.unique(lengths[mine], return_index=True, return_counts=True)
    gap = np.where((fill < capacity) & (fill >= fill[s]), capacity - fill, 0)
    gap[s] = 0
    widest = int(gap.max())
    fits = np.flatnonzero(sizes <= widest)
    if len(fits):  # a move: the longest piece that fits, where it leaves the least room
        k = fits[-1]
        targets = np.flatnonzero(gap >= sizes[k])
        return [int(mine[first[k]])], [], int(targets[np.argmin(gap[targets])])
    near = np.flatnonzero(gap[place] > 0)
    theirs, room = lengths[near], gap[place[near]]
    best, found = 0, None

    def exchange(shift: np.ndarray, room: np.ndarray) -> tuple[int, int]:
        """(shift, place) of the largest shift that the targets take."""
        shift = np.where(shift <= room, shift, 0)
        k = int(np.argmax(shift)) if len(shift) else 0
        return (int(shift[k]), k) if len(shift) else (0, 0)

    for k, size in zip(first.tolist(), sizes.tolist(), strict=True):  # one for one
        shift, at = exchange(size - theirs, room)
        if shift > best:
            best, found = shift, ([int(mine[k])], [int(near[at])], int(place[near[at]]))
    if found:
        return found
    pairs: dict[int, list[int]] = {}
    for i, k in enumerate(first.tolist()):
        for j in range(i, len(sizes)):
            if j > i or count[i] > 1:
                other = first[j] if j > i else np.flatnonzero(lengths[mine] == sizes[i])[1]
                pairs.setdefault(int(sizes[i] + sizes[j]), [int(mine[k]), int(mine[other])])
    for size, give in pairs.items():  # two for one
        shift, at = exchange(size - theirs, room)
        if shift > best:
            best, found = shift, (give, [int(near[at])], int(place[near[at]]))
    if found:
        return found
    order = near[np.lexsort([lengths[near], place[near]])]
    a, b = _pairs_within(place[order], lengths[order])
    both, room = lengths[order[a]] + lengths[order[b]], gap[place[order[a]]]
    for k, size in zip(first.tolist(), sizes.tolist(), strict=True):  # one for two
        shift, at = exchange(size - both, room)
        if shift > best:
            best, found = shift, ([int(mine[k])], [int(order[a[at]]), int(order[b[at]])], int(place[order[a[at]]]))
    return found


def _pairs_within(group: np.ndarray, length: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """All pairs of entries of one group, of pieces of one length at most two; groups and lengths ascend."""
    if not len(group):
        return np.zeros(0, dtype=np.int64), np.zeros(0, dtype=np.int64)
    same = np.concatenate([[False], (group[1:] == group[:-1]) & (length[1:] == length[:-1])])
    third = same & np.concatenate([[False], same[:-1]])
    own = np.flatnonzero(~third)
    g = group[own]
    left, right = [], []
    for step in range(1, len(own)):
        i = np.flatnonzero(g[step:] == g[:-step])
        if not len(i):
            break
        left.append(own[i])
        right.append(own[i + step])
    return (np.concatenate(left), np.concatenate(right)) if left else (own[:0], own[:0])


def pack_lengths(lengths: np.ndarray, capacity: int, last: bool = True) -> np.ndarray:
    """The sequence of each piece, numbered from 0 without gaps: best fit as they come, then the search.

    In the ``last`` pass, if that ends above the lower bound, the search starts once more from
    longest first, and the fewer sequences win.
    """
    if not len(lengths):
        return np.zeros(0, dtype=np.int64)
    place = np.unique(local_search(lengths, best_fit(lengths, capacity), capacity), return_inverse=True)[1]
    if last and place.max() + 1 > -(-int(lengths.sum()) // capacity):
        other = np.unique(local_search(lengths, best_fit_decreasing(lengths, capacity), capacity), return_inverse=True)[1]
        place = other if other.max() < place.max() else place
    return place


def _packed(table: pa.Table, capacity: int, base: int, last: bool) -> pa.Table:
    # in an order that has nothing to do with lengths, the same in whatever order the rows come
    order = np.lexsort([table["doc_id"].fill_null(0).to_numpy(), table["piece"].to_numpy(), table["ids_crc32"].to_numpy()])
    table = table.take(pa.array(order))
    lengths = table["length"].to_numpy().astype(np.int64)
    place = pack_lengths(lengths, capacity, last)
    order = np.argsort(place, kind="stable")
    table, lengths, place = table.take(pa.array(order)), lengths[order], place[order]
    before = np.cumsum(lengths) - lengths
    first = np.searchsorted(place, place)
    fill = np.bincount(place, weights=lengths).astype(np.int64)
    out = {n: table[n] for n in ("doc_id", "piece", "start", "length", "ids_crc32")}
    out |= {"sequence_id": base + place, "offset": before - before[first], "fill": fill[place] if len(place) else place}
    return pa.table(out)


def pack(pieces: DataFrame, n_docs: int, capacity: int = CAPACITY, group_docs: int = GROUP_DOCS) -> DataFrame:
    """Add sequence_id and offset to pieces.  ``n_docs``: about how many documents they come from.

    Pieces are dealt to groups by a hash of (doc_id, piece div 64), so a single huge document or a
    frequent length spreads over groups.  Sequences that a group leaves less than 98 % full are
    opened again and packed together with those of about FAN_IN other groups.
    """
    groups = max(1, -(-n_docs // group_docs))
    key = F.xxhash64("doc_id", F.floor(F.col("piece") / 64))
    schema = PACKED + ", fill long"

    def run(level: int):
        def pack_group(keys: tuple[pa.Scalar, ...], table: pa.Table) -> pa.Table:
            return _packed(table.select(["doc_id", "piece", "start", "length", "ids_crc32"]), capacity, (2 * keys[0].as_py() + level) << 32, level == 1 or groups == 1)

        return pack_group

    first = pieces.withColumn("grp", F.pmod(key, F.lit(groups))).groupBy("grp").applyInArrow(run(0), schema)
    if groups == 1:
        return first.drop("fill")
    first = written(first)
    full = F.col("fill") >= F.lit(capacity * 98 // 100)
    again = first.filter(~full).withColumn("grp", F.pmod(F.shiftright("sequence_id", 33), F.lit(-(-groups // FAN_IN))))
    return first.filter(full).unionByName(again.groupBy("grp").applyInArrow(run(1), schema)).drop("fill")


def packed_documents(docs: DataFrame, tokenizer_path: str, capacity: int = CAPACITY) -> DataFrame:
    """Tokenise, cut and pack whole documents; one row per piece."""
    pieces = written(token_pieces(docs, tokenizer_path, capacity))
    return pack(pieces, pieces.count(), capacity)


__all__ = ["CAPACITY", "WordTokenizer", "best_fit", "best_fit_decreasing", "local_search", "pack", "pack_lengths", "packed_documents", "removed", "token_pieces"]
