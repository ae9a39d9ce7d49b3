"""Exact Jaccard self-join of documents on word n-grams, as classes of linked documents.

1. Documents become sets of n-gram hashes; equal sets are one node from here on.
2. First matrix.  Tasks cut the rows into blocks; for every block the n-grams of its sets (shortened
   hashes) go to buckets, which count in how many sets each n-gram lies.  A set of s n-grams links
   only to sets that have at least threshold percent of s; sets with fewer n-grams that any other
   set holds too are linked with nothing and go no further.
3. Token groups.  What is left is dealt to groups of at most GROUP similar sets (equal smallest
   hash).  A group's members are matched at once; the group's token union goes to the second matrix,
   which tells for every n-gram how many unions have it.  A set's overlap with the unions of the
   other groups bounds that with any set in them; only sets that reach the bound stay open.
4. Open sets meet on their rarest n-grams (as counted over the unions): linked sets have a common
   one among the first s - need + 1.  Those that meet form classes, and a matrix of token groups
   decides within each class: a set's overlap with a group's union bounds that with every member,
   and only groups that pass are opened.  One link to a component is enough, so no group of copies
   is paired off.
5. Classes of more than BLOCK sets are dealt to blocks, each matched on its own.  What links to the
   class's first set, of which every block has a copy, is settled at once; the rest meets all sets
   of the class, block by block, in separate tasks, which stop at one link between two components.

Node keys and n-grams are 64-bit hashes; equal shortened hashes only leave more sets open.  ``docs``
must give the same rows at every read (a table, not a random sample).

Defined results: null and empty texts have no n-grams and are linked with nothing; a text shorter
than n words is one n-gram; a null doc_id takes part but never names a class that has others;
repeated rows are one class; an empty table gives no rows; other columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import zstandard
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from bitsort.llm.components import components
from bitsort.llm.stages import partitions, released, removed, written
from bitsort.llm.substring_dedup import _from_low_bytes, _pack_places, _pack_sorted, _unpack_sorted
from bitsort.llm.text import U64, Chunk, chunks, mix, release, sorted_unique, trim, window_hashes

NGRAM, THRESHOLD = 5, 80
GROUP, BLOCK = 512, 2000
#: N-grams are dealt to one bucket for so many documents, sets to one home for so many sets.
BUCKET_DOCS, HOME_SETS = 8_000, 500
BLOCK_BYTES = 24 << 20


def shingles(chunk: Chunk, n: int) -> Iterator[np.ndarray]:
    """The sorted distinct n-gram hashes of each document of a chunk."""
    words = chunk.hashes()
    runs = mix(window_hashes(words, n)) if len(words) >= n else words[:0]
    for i, j in zip(chunk.ptr[:-1].tolist(), chunk.ptr[1:].tolist(), strict=True):
        if j - i >= n:
            yield sorted_unique(runs[i : j - n + 1])
        else:
            yield mix(window_hashes(words[i:j], j - i)) if j > i else words[:0]


def set_key(tokens: np.ndarray) -> int:
    with np.errstate(over="ignore"):
        return int(mix(np.array([np.add.reduce(mix(tokens + U64(0x632BE59BD9B4E019)))], dtype=U64) + U64(len(tokens))).astype(np.int64)[0])


def least_hash(tokens: np.ndarray) -> int:
    """A value that sets of similarity j share with probability j."""
    return int(mix(tokens ^ U64(0x5851F42D4C957F2D)).min().astype(np.int64))


def needed(size: int, t: int) -> int:
    """So many n-grams of a set of ``size`` every set linked to it has."""
    return -(-t * size // 100)


def token_bits(docs: int) -> int:
    """Bits of shortened hashes: by chance about one n-gram in ten thousand meets another, at any size."""
    return min(64, max(docs, 1).bit_length() + 22)


def _cuts(values: np.ndarray, buckets: int, bits: int) -> list[int]:
    """Where each bucket's share of ascending ``values`` begins, and the end."""
    inner = np.searchsorted(values, np.array([(b << bits) // buckets for b in range(1, buckets)], dtype=U64)).tolist() if buckets > 1 else []
    return [0, *inner, len(values)]


def _ipc(batch: pa.RecordBatch) -> bytes:
    sink = pa.BufferOutputStream()
    with pa.ipc.new_stream(sink, batch.schema) as out:
        out.write_batch(batch)
    return zstandard.compress(sink.getvalue().to_pybytes(), 1)


def _rows(rows: list[tuple], schema: pa.Schema) -> pa.RecordBatch:
    cols = list(zip(*rows, strict=True)) or [[]] * len(schema)
    return pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip(cols, schema, strict=True)], schema=schema)


SKETCH = "bucket int, block long, docs binary, tokens binary, places binary"
_SKETCH = pa.schema([("bucket", pa.int32()), ("block", pa.int64()), ("docs", pa.binary()), ("tokens", pa.binary()), ("places", pa.binary())])
_DOCS = pa.schema([("doc_id", pa.int64()), ("text_hash", pa.int64()), ("n_shingles", pa.int64()), ("node", pa.int64()), ("place", pa.int32())])


class _SketchBlock:
    """Rows of one task and the distinct sets among them."""

    def __init__(self, key: int):
        self.key, self.rows, self.place_of, self.tokens, self.bytes = key, [], {}, [], 0

    def add(self, doc_id: int | None, text_hash: int, tokens: np.ndarray, shift: U64) -> None:
        if not len(tokens):
            self.rows.append((doc_id, text_hash, 0, None, None))
            return
        node = set_key(tokens)
        place = self.place_of.setdefault(node, len(self.place_of))
        if place == len(self.tokens):
            self.tokens.append(tokens >> shift)
        self.rows.append((doc_id, text_hash, len(tokens), node, place))

    def messages(self, buckets: int, bits: int) -> pa.RecordBatch:
        """The rows, for one bucket to pass on, and every bucket's share of the sets' n-grams."""
        out = [(self.key % buckets, self.key, _ipc(_rows(self.rows, _DOCS)), None, None)]
        if self.tokens:
            place = np.repeat(np.arange(len(self.tokens), dtype=np.uint32), [len(x) for x in self.tokens])
            values = np.concatenate(self.tokens)
            order = np.argsort(values, kind="stable")
            values, place = values[order], place[order]
            edges = _cuts(values, buckets, bits)
            out += [(b, self.key, None, _pack_sorted(values[i:j]), _pack_places(place[i:j])) for b, (i, j) in enumerate(zip(edges, edges[1:], strict=False)) if j > i]
        return _rows(out, _SKETCH)


def _sketch(n: int, buckets: int, bits: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        release()
        shift, first = U64(64 - bits), TaskContext.get().partitionId() << 24
        made, block = 0, _SketchBlock(first)
        for batch in batches:
            ids, hashes = batch.column(0).to_pylist(), batch.column(1).to_pylist()
            for chunk in chunks(batch.column(2), lower=True):
                for k, tokens in enumerate(shingles(chunk, n), chunk.first):
                    block.add(ids[k], hashes[k], tokens, shift)
                block.bytes += len(chunk.data)
                if block.bytes >= BLOCK_BYTES:
                    yield block.messages(buckets, bits)
                    made += 1
                    block = _SketchBlock(first + made)
                    trim()
        if block.rows:
            yield block.messages(buckets, bits)

    return run


def _count_shared(table: pa.Table) -> pa.Table:
    """For the sets of every block, how many n-grams of this bucket another set has too."""
    passed, keys, values, owners, sizes = [], [], [], [], []
    for block, docs, tokens, places in zip(*(table[c].to_pylist() for c in ("block", "docs", "tokens", "places")), strict=True):
        if docs is not None:
            passed.append((block, docs, None))
            continue
        own = _from_low_bytes(places[1:], places[0]).astype(np.int64)
        keys.append(block)
        values.append(_unpack_sorted(tokens))
        owners.append(own + sum(sizes[-1:]))
        sizes.append(sum(sizes[-1:]) + int(own.max()) + 1)
    out = passed
    if values:
        value, owner = np.concatenate(values), np.concatenate(owners)
        values = owners = None
        order = np.argsort(value, kind="stable")
        value, owner = value[order], owner[order]
        del order
        equal = value[1:] == value[:-1]
        common = np.concatenate([[False], equal]) | np.concatenate([equal, [False]])
        counts = np.bincount(owner[common], minlength=sizes[-1]).astype(np.uint32)
        for key, i, j in zip(keys, [0, *sizes[:-1]], sizes, strict=True):
            out.append((key, None, zstandard.compress(counts[i:j].tobytes(), 1)))
        del value, owner, common
    trim()
    cols = list(zip(*out, strict=True)) or [[]] * 3
    return pa.table([pa.array(c, t) for c, t in zip(cols, (pa.int64(), pa.binary(), pa.binary()), strict=True)], ["block", "docs", "counts"])


def _totals(table: pa.Table) -> pa.Table:
    """The rows of one block, each with the number of n-grams that other sets have too."""
    counts = [np.frombuffer(zstandard.decompress(x), np.uint32) for x in table["counts"].to_pylist() if x is not None]
    total = np.zeros(max((len(c) for c in counts), default=0) + 1, dtype=np.int64)
    for c in counts:
        total[: len(c)] += c
    docs = pa.ipc.open_stream(zstandard.decompress(next(x for x in table["docs"].to_pylist() if x is not None))).read_all()
    place = docs["place"].fill_null(-1).to_numpy()
    return docs.drop_columns(["place"]).append_column("shared", pa.array(np.where(place < 0, 0, total[np.minimum(place, len(total) - 1)])))


UNION = "bucket int, home int, tokens binary"
OPEN = "kind int, a long, b long, bucket int, nodes binary, signatures binary, places binary"
_OPEN = pa.schema([("kind", pa.int32()), ("a", pa.int64()), ("b", pa.int64()), ("bucket", pa.int32()), ("nodes", pa.binary()), ("signatures", pa.binary()), ("places", pa.binary())])
#: Kinds of rows: a link that is sure, two sets that meet, what a home has for one bucket.
LINK, MEET, RAREST = 0, 1, 2


def _grouped(table: pa.Table) -> tuple[np.ndarray, list[np.ndarray], list[tuple[int, int]]]:
    """(nodes, sets, groups as ranges) of a home, the same whatever the order of its rows."""
    order = np.lexsort([table["node"].to_numpy(), table["first"].to_numpy()])
    node, first = table["node"].to_numpy()[order], table["first"].to_numpy()[order]
    once = np.concatenate([[True], (node[1:] != node[:-1]) | (first[1:] != first[:-1])]) if len(node) else np.zeros(0, dtype=bool)
    order, node, first = order[once], node[once], first[once]
    tokens = table["tokens"].to_pylist()
    sets = [np.frombuffer(tokens[i], np.int64).view(U64) for i in order.tolist()]
    edges = np.flatnonzero(np.concatenate([[True], first[1:] != first[:-1], [True]])).tolist() if len(node) else [0]
    return node, sets, [(k, min(k + GROUP, j)) for i, j in zip(edges, edges[1:], strict=False) for k in range(i, j, GROUP)]


def _union_values(sets: list[np.ndarray], groups: list[tuple[int, int]], bits: int) -> np.ndarray:
    """The shortened n-grams of every group's union, ascending; one entry for each group that has one."""
    unions = [sets[i] >> U64(64 - bits) if j == i + 1 else np.concatenate(sets[i:j]) >> U64(64 - bits) for i, j in groups]
    return np.sort(np.concatenate([sorted_unique(u) for u in unions])) if unions else np.zeros(0, dtype=U64)


def _union_messages(buckets: int, bits: int):
    def run(table: pa.Table) -> pa.Table:
        _, sets, groups = _grouped(table)
        values = _union_values(sets, groups, bits)
        edges, home = _cuts(values, buckets, bits), table["home"][0].as_py()
        rows = [(b, home, _pack_sorted(values[i:j])) for b, (i, j) in enumerate(zip(edges, edges[1:], strict=False)) if j > i]
        del sets, values
        trim()
        return pa.Table.from_batches([_rows(rows, pa.schema([("bucket", pa.int32()), ("home", pa.int32()), ("tokens", pa.binary())]))])

    return run


def _count_groups(table: pa.Table) -> pa.Table:
    """For every entry of a home, how many groups' unions have that n-gram (255: that many or more)."""
    homes, buckets, values = (table[c].to_pylist() for c in ("home", "bucket", "tokens"))
    values = [_unpack_sorted(x) for x in values]
    sizes = np.cumsum([len(v) for v in values]).tolist()
    value = np.concatenate(values)
    values = None
    order = np.argsort(value, kind="stable")
    value = value[order]
    first = np.flatnonzero(np.concatenate([[True], value[1:] != value[:-1]]))
    run = np.diff(np.append(first, len(value)))
    counts = np.empty(len(value), dtype=np.uint8)
    counts[order] = np.repeat(np.minimum(run, 255), run)
    del value, order
    trim()
    rows = [(h, b, zstandard.compress(counts[i:j].tobytes(), 1)) for h, b, i, j in zip(homes, buckets, [0, *sizes[:-1]], sizes, strict=True)]
    return pa.Table.from_batches([_rows(rows, pa.schema([("home", pa.int32()), ("bucket", pa.int32()), ("counts", pa.binary())]))])


def _open_sets(t: int, buckets: int, bits: int):
    """Links inside the groups of a home, and the rarest n-grams of the sets that stay open."""

    def run(table: pa.Table, replies: pa.Table) -> pa.Table:
        if not table.num_rows:
            return pa.Table.from_batches([_rows([], _OPEN)])
        node, sets, groups = _grouped(table)
        values = _union_values(sets, groups, bits)
        told = sorted(zip(replies["bucket"].to_pylist(), replies["counts"].to_pylist(), strict=True))
        counts = np.concatenate([np.frombuffer(zstandard.decompress(c), np.uint8) for _, c in told])
        rows: list[tuple] = []
        for i, j in groups:
            if j > i + 1:
                own, sizes, width = shared_columns(sets[i:j])
                matrix = TokenGroups(t, width)
                _match(matrix, own, sizes)
                rows += [(LINK, int(node[i + matrix.root(k)]), int(node[i + k]), None, None, None, None) for k in range(j - i) if matrix.root(k) != k]
        sent, places = [], []
        for k, tokens in enumerate(sets):
            unions = counts[np.searchsorted(values, tokens >> U64(64 - bits))]
            need = needed(len(tokens), t)
            elsewhere = int((unions > 1).sum())
            if elsewhere >= need:
                rarest = np.argsort(unions, kind="stable")[len(tokens) - elsewhere : len(tokens) - need + 1]  # tokens ascend, so ties do
                sent.append(tokens[rarest])
                places.append(np.full(len(rarest), k))
        if sent:
            value, place = np.concatenate(sent), np.concatenate(places)
            order = np.lexsort([node[place], value])
            value, owner = value[order], node[place[order]]
            first = np.flatnonzero(np.concatenate([[True], value[1:] != value[:-1]]))
            least = np.repeat(owner[first], np.diff(np.append(first, len(value))))
            meet = np.unique(np.stack([least, owner], axis=1)[least != owner], axis=0)  # of a common n-gram one set is sent on
            rows += [(MEET, a, b, None, None, None, None) for a, b in meet.tolist()]
            value, owner = value[first], owner[first]
            edges = _cuts(value, buckets, 64)
            for b, (i, j) in enumerate(zip(edges, edges[1:], strict=False)):
                if j > i:
                    known, at = np.unique(owner[i:j], return_inverse=True)
                    rows.append((RAREST, None, None, b, known.tobytes(), _pack_sorted(value[i:j]), _pack_places(at)))
        del sets, values, counts
        trim()
        return pa.Table.from_batches([_rows(rows, _OPEN)])

    return run


def _candidate_pairs(table: pa.Table) -> pa.Table:
    """A forest over the nodes that share signatures: (smallest node, other node)."""
    sigs, nodes = [], []
    for known, s, p in zip(*(table[c].to_pylist() for c in ("nodes", "signatures", "places")), strict=True):
        sigs.append(_unpack_sorted(s))
        nodes.append(np.frombuffer(known, np.int64)[_from_low_bytes(p[1:], p[0]).astype(np.int64)])
    sig, node = np.concatenate(sigs), np.concatenate(nodes)
    sigs = nodes = None
    order = np.argsort(sig)
    sig, node = sig[order], node[order]
    del order
    new = np.concatenate([[True], sig[1:] != sig[:-1]])
    least = np.minimum.reduceat(node, np.flatnonzero(new))[np.cumsum(new) - 1]
    trim()
    star = np.unique(np.stack([least, node], axis=1)[least != node], axis=0) if (least != node).any() else np.zeros((0, 2), dtype=np.int64)
    # of the bucket's stars a spanning forest says as much
    parent: dict[int, int] = {}

    def root(x: int) -> int:
        while (up := parent.setdefault(x, x)) != x:
            parent[x] = x = parent[up]
        return x

    for a, b in star.tolist():
        a, b = root(a), root(b)
        if a != b:
            parent[max(a, b)] = min(a, b)
    forest = [(root(x), x) for x in parent if root(x) != x]
    return pa.table([pa.array([r[k] for r in forest], pa.int64()) for k in (0, 1)], ["a", "b"])


class TokenGroups:
    """Sets in groups of similar ones, and a matrix that tells which n-grams each group's union has.

    The matrix has a row a group and a bit an n-gram that two sets or more of the task share.
    """

    def __init__(self, t: int, width: int):
        self.t, self.width = t, width
        self.sets: list[np.ndarray] = []  # columns of each set's shared n-grams
        self.sizes: list[int] = []
        self.parent: list[int] = []  # union-find over sets
        self.group_at: list[int] = []
        self.members: list[list[int]] = []
        self.unions = np.zeros((8, (width + 7) // 8), dtype=np.uint8)
        self.mark = np.zeros(width, dtype=bool)

    def root(self, i: int) -> int:
        while self.parent[i] != i:
            self.parent[i] = self.parent[self.parent[i]]
            i = self.parent[i]
        return i

    def similar(self, i: int, own: np.ndarray, size: int, both: int) -> bool:
        return 100 * both >= self.t * (size + self.sizes[i] - both)

    def linked(self, own: np.ndarray, size: int, skip: set[int]) -> list[int]:
        """One linked set of every component (but those in ``skip``) that has one."""
        need = -(-self.t * size // 100)  # a linked set has so much of this one
        if not self.members or len(own) < need:
            return []
        overlap = ((self.unions[: len(self.members), own >> 3] >> (own & 7).astype(np.uint8)) & 1).sum(axis=1)
        self.mark[own] = True
        found, done = [], set(skip)
        for g in np.flatnonzero(overlap >= need)[np.argsort(-overlap[overlap >= need], kind="stable")].tolist():
            for i in self.members[g]:
                if (root := self.root(i)) in done or self.t * max(size, self.sizes[i]) > 100 * min(size, self.sizes[i]):
                    continue
                if self.similar(i, own, size, int(self.mark[self.sets[i]].sum())):
                    found.append(i)
                    done.add(root)
        self.mark[own] = False
        return found

    def add(self, own: np.ndarray, size: int, near: int | None = None) -> int:
        """Put a set into the group of ``near`` if that has room, else into a new one."""
        i = len(self.sets)
        self.sets.append(own)
        self.sizes.append(size)
        self.parent.append(i)
        g = self.group_at[near] if near is not None else None
        if g is None or len(self.members[g]) >= GROUP:
            g = len(self.members)
            self.members.append([])
            if g == len(self.unions):
                self.unions = np.concatenate([self.unions, np.zeros_like(self.unions)])
        self.members[g].append(i)
        self.group_at.append(g)
        np.bitwise_or.at(self.unions[g], own >> 3, np.left_shift(1, own & 7).astype(np.uint8))
        return i

    def join(self, i: int, j: int) -> None:
        i, j = self.root(i), self.root(j)
        self.parent[max(i, j)] = min(i, j)


def shared_columns(own: list[np.ndarray]) -> tuple[list[np.ndarray], list[int], int]:
    """(shared n-grams of each set as columns, sizes, number of columns)."""
    sizes = [len(x) for x in own]
    flat = np.concatenate(own) if own else np.zeros(0, dtype=U64)
    _, column, count = np.unique(flat, return_inverse=True, return_counts=True)
    shared = count >= 2
    number = np.cumsum(shared) - 1
    keep = shared[column]
    ends = np.cumsum(sizes)[:-1] if sizes else []
    parts = np.split(number[column].astype(np.int32), ends) if sizes else []
    return [p[k] for p, k in zip(parts, np.split(keep, ends) if sizes else [], strict=True)], sizes, int(shared.sum())


def _sets(table: pa.Table) -> tuple[list[np.ndarray], list[int], int]:
    return shared_columns([np.frombuffer(x, np.int64) for x in table["tokens"].to_pylist()])


def _match(groups: TokenGroups, sets: list[np.ndarray], sizes: list[int]) -> None:
    """Add all sets and join those that are linked."""
    for own, size in zip(sets, sizes, strict=True):
        hits = groups.linked(own, size, set())
        i = groups.add(own, size, hits[0] if hits else None)
        for j in hits:
            groups.join(i, j)


def _match_class(t: int):
    """All sets of one class of candidates: (node, label), label the smallest linked node."""

    def run(table: pa.Table) -> pa.Table:
        table = table.sort_by("node")  # so labels do not depend on the order of arrival
        nodes = table["node"].to_pylist()
        sets, sizes, width = _sets(table)
        groups = TokenGroups(t, width)
        _match(groups, sets, sizes)
        return pa.table([pa.array(nodes, pa.int64()), pa.array([nodes[groups.root(i)] for i in range(len(nodes))], pa.int64())], ["node", "label"])

    return run


MATCHED = "class long, block int, node long, label long, settled boolean, tokens binary"


def _match_block(t: int):
    """One block of a large class, and which of its components link to the class's first set."""

    def run(table: pa.Table) -> pa.Table:
        # the first set comes last, after all sets of the block; in its own block it is there twice
        table = table.sort_by([("first", "ascending"), ("node", "ascending")])
        is_first = table["first"].to_pylist()
        n = is_first.index(True) if True in is_first else len(is_first)
        sets, sizes, width = _sets(table)
        groups = TokenGroups(t, width)
        _match(groups, sets[:n], sizes[:n])
        table = table.slice(0, n)
        nodes, roots = table["node"].to_pylist(), [groups.root(i) for i in range(n)]
        settled = {groups.root(i) for i in groups.linked(sets[n], sizes[n], set())} if n < len(sets) else set()
        return pa.table(
            [table["class"], table["block"], table["node"], pa.array([nodes[r] for r in roots], pa.int64()), pa.array([r in settled for r in roots], pa.bool_()), table["tokens"]],
            ["class", "block", "node", "label", "settled", "tokens"],
        )

    return run


def _match_blocks(t: int):
    """Unsettled sets against the sets of one block: a link (a, b) for each two linked components."""

    def run(table: pa.Table) -> pa.Table:
        table = table.sort_by([("query", "ascending"), ("node", "ascending")])
        query, nodes = table["query"].to_pylist(), table["node"].to_pylist()
        labels, settled = table["label"].to_pylist(), table["settled"].to_pylist()
        sets, sizes, width = _sets(table)
        n = query.index(True) if True in query else len(query)
        groups, at = TokenGroups(t, width), {}
        for k in range(n):
            key = None if settled[k] else labels[k]  # what is settled is one component
            i = groups.add(sets[k], sizes[k], at.get(key))
            if key in at:
                groups.join(i, at[key])
            at.setdefault(key, i)
        every = {groups.root(i) for i in range(n)}
        done: dict[int, set[int]] = {}
        links = []
        for k in range(n, len(nodes)):
            known = done.setdefault(labels[k], {groups.root(at[labels[k]])} if labels[k] in at else set())
            if len(known) < len(every):
                for j in groups.linked(sets[k], sizes[k], known):
                    links.append((nodes[k], nodes[j]))
                    known.add(groups.root(j))
        cols = list(zip(*links, strict=True)) or [[], []]
        del groups, sets
        trim()
        return pa.table([pa.array(c, pa.int64()) for c in cols], ["a", "b"])

    return run


def _match_large(sets: DataFrame, sizes: DataFrame, t: int) -> DataFrame:
    """(node, label) of classes with more than BLOCK sets."""
    n = 4 * partitions(sets.sparkSession)  # an own count, or the few rows of costly blocks were put into one task
    blocks = lambda c: F.greatest(F.lit(1), F.ceil(F.col(c) / BLOCK)).cast("int")
    every = lambda c: F.explode(F.sequence(F.lit(0), blocks(c) - 1))
    dealt = sets.join(sizes, "class")
    own = dealt.select("class", F.pmod(F.xxhash64("node"), blocks("sets")).cast("int").alias("block"), "node", "tokens", F.lit(False).alias("first"))
    first = dealt.filter(F.col("node") == F.col("class")).select("class", every("sets").alias("block"), "node", "tokens", F.lit(True).alias("first"))
    told = own.unionByName(first).repartition(n, "class", "block").groupBy("class", "block").applyInArrow(_match_block(t), MATCHED)
    told = written(told)
    links = told.select(F.col("label").alias("a"), F.col("node").alias("b")).unionByName(told.filter("settled").select(F.col("class").alias("a"), F.col("node").alias("b")))
    open_sizes = told.filter("not settled").groupBy("class").agg(F.count(F.lit(1)).alias("open"))
    both = told.join(sizes, "class").join(open_sizes, "class")
    cols = ("class", "node", "label", "settled", "tokens")
    members = both.select(*cols, F.lit(False).alias("query"), every("open").alias("i"), F.col("block").alias("j"))
    asking = both.filter("not settled").select(*cols, F.lit(True).alias("query"), F.pmod(F.xxhash64("node"), blocks("open")).cast("int").alias("i"), every("sets").alias("j"))
    more = members.unionByName(asking).repartition(n, "class", "i", "j").groupBy("class", "i", "j").applyInArrow(_match_blocks(t), "a long, b long")
    return components(links.unionByName(more))


#: Up to so many large classes are named in a broadcast.
BROADCAST_CLASSES = 100_000


def _matched(sets: DataFrame, t: int) -> DataFrame:
    """(node, label) of sets (class, node, tokens), class by class."""
    sizes = sets.groupBy("class").agg(F.count(F.lit(1)).alias("sets"))
    large = written(sizes.filter(F.col("sets") > BLOCK))
    n_large = large.count()
    if not n_large:
        return sets.groupBy("class").applyInArrow(_match_class(t), "node long, label long")
    large = F.broadcast(large) if n_large <= BROADCAST_CLASSES else large
    out = sets.join(large, "class", "left_anti").groupBy("class").applyInArrow(_match_class(t), "node long, label long")
    return out.unionByName(_match_large(sets.join(large, "class", "left_semi"), large, t))


def _regain(n: int):
    """Sets of the documents that name a node."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for chunk in chunks(batch.column(1), lower=True):
                tokens = list(shingles(chunk, n))
                own = batch.slice(chunk.first, len(tokens))
                first = pa.array([least_hash(x) for x in tokens], pa.int64())
                yield pa.RecordBatch.from_arrays([own.column(0), first, pa.array([x.tobytes() for x in tokens], pa.binary())], ["node", "first", "tokens"])

    return run


def near_duplicates(docs: DataFrame, n: int = NGRAM, threshold: int = THRESHOLD) -> DataFrame:
    """doc_id, text_hash, n_shingles, component_id for every row of ``docs``."""
    spark = docs.sparkSession
    rows = docs.select(F.col("doc_id").cast("long"), F.xxhash64("text").alias("text_hash"), F.col("text").cast("string"))
    n_docs = docs.count()
    buckets, bits = max(1, -(-n_docs // BUCKET_DOCS)), token_bits(n_docs)
    counted = rows.mapInArrow(_sketch(n, buckets, bits), SKETCH).groupBy("bucket").applyInArrow(_count_shared, "block long, docs binary, counts binary")
    of_docs = written(counted.groupBy("block").applyInArrow(_totals, "doc_id long, text_hash long, n_shingles long, node long, shared long"))
    del counted
    released(spark)
    # one document of each set that others may link to gives its n-grams once more
    key = [F.coalesce("doc_id", F.lit(-1)).alias("k"), F.col("text_hash")]
    reps = of_docs.filter(F.col("node").isNotNull() & (100 * F.col("shared") >= threshold * F.col("n_shingles"))).groupBy("node").agg(F.min(F.struct("doc_id", "text_hash")).alias("r"))
    texts = rows.select(*key, "text").join(reps.select("node", "r.*").select(*key, "node"), ["k", "text_hash"]).select("node", "text")
    sets = written(texts.mapInArrow(_regain(n), "node long, first long, tokens binary"))
    del texts, reps
    released(spark)
    # homes hold whole groups; sets with a frequent smallest hash spread over several
    n_sets = sets.count()
    homes = max(1, -(-n_sets // HOME_SETS))
    hot = sets.groupBy("first").agg(F.count(F.lit(1)).alias("n")).filter(F.col("n") > HOME_SETS)
    part = F.pmod(F.xxhash64("node"), F.coalesce(F.ceil(F.col("n") / HOME_SETS), F.lit(1)))
    homed = sets.join(hot, "first", "left").select(F.pmod(F.xxhash64("first", part), F.lit(homes)).cast("int").alias("home"), "node", "first", "tokens")
    replies = homed.groupBy("home").applyInArrow(_union_messages(buckets, bits), UNION).groupBy("bucket").applyInArrow(_count_groups, "home int, bucket int, counts binary")
    told = written(homed.groupBy("home").cogroup(replies.groupBy("home")).applyInArrow(_open_sets(threshold, buckets, bits), OPEN))
    del homed, replies
    pairs = told.filter(F.col("kind") == RAREST).select("bucket", "nodes", "signatures", "places").groupBy("bucket").applyInArrow(_candidate_pairs, "a long, b long")
    classes = components(pairs.unionByName(told.filter(F.col("kind") == MEET).select("a", "b"))).select("node", F.col("label").alias("class"))
    open_sets = written(sets.join(classes, "node").select("class", "node", "tokens"))
    removed(sets)
    del pairs, classes, sets
    released(spark)
    sure = told.filter(F.col("kind") == LINK).select("a", "b")
    labels = written(components(sure.unionByName(_matched(open_sets, threshold).select(F.col("label").alias("a"), F.col("node").alias("b")))))
    removed(open_sets, told)
    nodes = of_docs.filter("node is not null").groupBy("node").agg(F.min("doc_id").alias("rep"))
    named = labels.join(nodes, "node")
    least = named.groupBy("label").agg(F.min("rep").alias("least"))
    final = nodes.join(named.select("node", "label").join(least, "label").select("node", "least"), "node", "left").select("node", F.coalesce("least", "rep").alias("component"))
    return of_docs.join(final, "node", "left").select("doc_id", "text_hash", "n_shingles", F.coalesce("component", "doc_id").alias("component_id"))


def kept_documents(docs: DataFrame, n: int = NGRAM, threshold: int = THRESHOLD) -> DataFrame:
    """The rows of ``docs`` without near duplicates: of each class the document with the smallest doc_id."""
    told = near_duplicates(docs, n, threshold).filter("component_id is null or doc_id = component_id").select("doc_id", "text_hash")
    told = told.groupBy("doc_id", "text_hash").agg(F.count(F.lit(1)).alias("_copies"))
    alone = F.when(F.col("doc_id").isNull(), F.col("text_hash"))  # rows without an id are told apart by their text
    first = written(told).groupBy("doc_id", alone.alias("_alone")).agg(F.min("text_hash").alias("text_hash"), F.max("_copies").alias("_copies"), F.count(F.lit(1)).alias("_texts"))
    own = docs.withColumn("_h", F.xxhash64("text"))
    match = first.select(F.col("doc_id").alias("_d"), F.col("text_hash").alias("_t"))
    out = own.join(match, own["doc_id"].eqNullSafe(match["_d"]) & (own["_h"] == match["_t"]), "left_semi")
    if not first.filter("_copies > 1 or _texts > 1").isEmpty():
        out = out.dropDuplicates(["doc_id", "_h"])
    return out.select(*docs.columns)
