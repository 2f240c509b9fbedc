"""Similarity join of word n-gram sets by a prefix tree.

Sets are sequences of 64-bit shingle keys in one global order, rare shingles first. Four steps, each exact:

1. Which shingles occur in two texts or more: counted over all shingles, dealt out by hash. A text
   can only have a partner if three quarters of its set are such shared shingles.
2. Texts that pass are reduced to one per distinct set, ordered by how many sets hold a shingle,
   and sets that share a shingle within the
   prefix that any two similar sets must share are candidates; their components become blocks.
3. In a block the ordered sets form a compressed trie. A probe walks it level by level: sets with
   a common beginning share the overlap counted there, and a subtree is left as soon as what
   remains of probe and subtree cannot reach the similarity. Blocks beyond a bound are joined as
   pairs of chunks.
4. Links give components, whose smallest doc_id is the answer.
"""

from __future__ import annotations

import hashlib
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import bucket_count, discard, first_columns, map_arrow, materialise, ship_package, slices, text_bytes
from .components import connected, local_stars

WORDS = 5
PERCENT = 75
#: Members of a block's chunk, and bytes of their payloads, at most (one member at least).
BLOCK_SETS, BLOCK_BYTES = 1024, 16 << 20
#: Payload bytes of whole blocks that are solved together.
SOLVE_BYTES = 1 << 20
#: Shingles on one edge of the trie at most.
EDGE = 48
_MARK = 0xFFFF  # in place of a text's number: the shingle is in several texts of that slice
_KEYS = np.array([0x9E3779B97F4A7C15, 0xC2B2AE3D27D4EB4F, 0x165667B19E3779F9, 0xD6E8FEB86659FD93, 0xA0761D6478BD642F], dtype=np.uint64)


def mix(h: np.ndarray) -> np.ndarray:
    """A bijective scrambling of 64-bit numbers."""
    with np.errstate(over="ignore"):
        h = (h ^ (h >> np.uint64(32))) * np.uint64(0xD6E8FEB86659FD93)
        h = (h ^ (h >> np.uint64(29))) * np.uint64(0xA0761D6478BD642F)
        return h ^ (h >> np.uint64(32))


class WordHashes(dict):
    """64-bit hash of each word, kept while the worker has room."""

    def __missing__(self, word: bytes) -> int:
        if len(self) > 100_000:
            self.clear()
        found = self[word] = xxhash.xxh3_64_intdigest(word)
        return found


def shingle_set(text: bytes, hashes: WordHashes, words: int = WORDS) -> np.ndarray:
    """Sorted distinct hashes of the word shingles of a text; of the whole sequence where it has
    fewer words; empty without words. A-Z are lower-cased, words end at ASCII white space."""
    found = text.lower().split()
    n = len(found)
    if not n:
        return np.zeros(0, dtype=np.uint64)
    ids = np.fromiter(map(hashes.__getitem__, found), np.uint64, n)
    width = min(words, n)
    with np.errstate(over="ignore"):
        total = np.zeros(n - width + 1, dtype=np.uint64)
        for k in range(width):
            total += mix(ids[k : n - width + 1 + k] * _KEYS[k % 5] + np.uint64(k + 1)) if words > 5 else ids[k : n - width + 1 + k] * _KEYS[k]
        total += np.uint64(width)
    return np.unique(mix(total))


def required_overlap(a: np.ndarray | int, b: np.ndarray | int, percent: int = PERCENT) -> np.ndarray | int:
    """Smallest overlap with which sets of these sizes are similar."""
    return -(-percent * (a + b) // (100 + percent))


class SetTrie:
    """Ordered sets in a compressed trie: an edge holds the run of shingles that its sets share.

    ``order`` lists the sets as the trie's leaves from left to right. Each node covers a range of
    leaves; nodes are grouped by level so that a walk handles a level at once.
    """

    def __init__(self, sets: list[np.ndarray]):
        keys = [s.astype(">u8").tobytes() for s in sets]
        self.order = np.array(sorted(range(len(sets)), key=keys.__getitem__), dtype=np.int64)
        ordered = [sets[i] for i in self.order]
        self.sizes = np.array([len(s) for s in ordered], dtype=np.int64)
        common = [0] * (len(ordered) + 1)
        for i in range(1, len(ordered)):
            a, b = ordered[i - 1], ordered[i]
            k = min(len(a), len(b))
            different = np.flatnonzero(a[:k] != b[:k])
            common[i] = int(different[0]) if len(different) else k
        edges: list[np.ndarray] = []
        first, last, depth, level, children = [], [], [], [], []

        def grow(lo: int, hi: int, start: int, at: int) -> None:
            todo = [(lo, hi, start, at, -1)]
            while todo:
                lo, hi, start, at, parent = todo.pop()
                whole = min(common[lo + 1 : hi]) if hi - lo > 1 else int(self.sizes[lo])
                shared = min(whole, start + EDGE)  # a long run is a chain of nodes: a walk can leave it early
                node = len(edges)
                edges.append(ordered[lo][start:shared])
                first.append(lo), last.append(hi), depth.append(shared), level.append(at), children.append([])
                if parent >= 0:
                    children[parent].append(node)
                if shared < whole:
                    todo.append((lo, hi, shared, at + 1, node))
                elif hi - lo > 1:
                    cuts = [lo, *[i for i in range(lo + 1, hi) if common[i] == shared], hi]
                    todo += [(a, b, shared, at + 1, node) for a, b in zip(cuts, cuts[1:]) if b - a < hi - lo]

        grow(0, len(ordered), 0, 0)
        self.first, self.last, self.depth = (np.array(x, dtype=np.int64) for x in (first, last, depth))
        self.tokens = np.concatenate(edges)
        self.start = np.concatenate([[0], np.cumsum([len(e) for e in edges])])
        self.child_start = np.concatenate([[0], np.cumsum([len(c) for c in children])])
        self.child = np.array([c for group in children for c in group], dtype=np.int64)
        self.least = np.array([self.sizes[a:b].min() for a, b in zip(first, last)], dtype=np.int64)
        self.most = np.array([self.sizes[a:b].max() for a, b in zip(first, last)], dtype=np.int64)

    def walk(self, probe: np.ndarray, wanted: np.ndarray, percent: int = PERCENT) -> np.ndarray:
        """Wanted leaves whose sets are similar to ``probe``. ``wanted``: a flag for each leaf."""
        n = len(probe)
        before = np.concatenate([[0], np.cumsum(wanted)])
        nodes, overlap, hits = np.array([0]), np.array([0]), []
        while len(nodes):
            begin, length = self.start[nodes], self.start[nodes + 1] - self.start[nodes]
            spans = np.repeat(begin - np.concatenate([[0], np.cumsum(length)[:-1]]), length) + np.arange(int(length.sum()))
            run = self.tokens[spans]
            at = np.searchsorted(probe, run)
            member = np.zeros(len(run) + 1, dtype=np.int64)
            member[1:] = np.cumsum(probe[np.minimum(at, n - 1)] == run)
            ends = np.cumsum(length)
            overlap = overlap + member[ends] - member[ends - length]
            # what is left of the probe after the edge's last shingle
            passed = np.zeros(len(nodes), dtype=np.int64)
            deep = self.depth[nodes] > 0
            tail = self.tokens[np.maximum(self.start[nodes + 1] - 1, 0)]
            full = deep & (length > 0)
            passed[full] = np.searchsorted(probe, tail[full], "right")
            best = overlap + np.minimum(n - passed, self.most[nodes] - self.depth[nodes])
            alive = (best >= required_overlap(n, self.least[nodes], percent)) & (100 * self.most[nodes] >= percent * n) & (percent * self.least[nodes] <= 100 * n) & (before[self.last[nodes]] > before[self.first[nodes]])
            nodes, overlap = nodes[alive], overlap[alive]
            count = self.child_start[nodes + 1] - self.child_start[nodes]
            ended = np.flatnonzero(overlap >= required_overlap(n, self.depth[nodes], percent))
            for k in ended:  # sets that end at this node: equal ones lie side by side, first in its range
                lo, hi = self.first[nodes[k]], self.last[nodes[k]]
                stop = hi if not count[k] else self.first[self.child[self.child_start[nodes[k]]: self.child_start[nodes[k] + 1]]].min()
                leaves = np.arange(lo, stop)
                hits.append(leaves[wanted[lo:stop] & (self.sizes[lo:stop] == self.depth[nodes[k]])])
            offset = np.repeat(self.child_start[nodes] - np.concatenate([[0], np.cumsum(count)[:-1]]), count) + np.arange(int(count.sum()))
            nodes, overlap = self.child[offset], np.repeat(overlap, count)
        return np.concatenate(hits) if hits else np.zeros(0, dtype=np.int64)


def similar_groups(sets: list[np.ndarray], percent: int = PERCENT, sides: np.ndarray | None = None) -> np.ndarray:
    """Smallest member of each set's component under similarity.

    A probe asks only for sets of other components so far, since links inside one tell nothing
    new. With ``sides``, only pairs from different sides are asked for.
    """
    m = len(sets)
    label = np.arange(m)
    if m < 2:
        return label
    # within a block the order may be the block's own: rare shingles first, by rank
    lengths = np.array([len(s) for s in sets])
    names, times = np.unique(np.concatenate(sets), return_inverse=True, return_counts=True)[1:]
    rank = np.empty(len(times), dtype=np.uint64)
    rank[np.argsort(times, kind="stable")] = np.arange(len(times), dtype=np.uint64)
    stops = np.cumsum(lengths)
    ranked = rank[names]
    sets = [np.sort(ranked[b - n : b]) for b, n in zip(stops.tolist(), lengths.tolist(), strict=True)]
    # sets that share no shingle of their prefixes cannot be similar and are not asked for
    heads = [s[: len(s) + (-percent * len(s) // 100) + 1] for s in sets]
    names = np.unique(np.concatenate(heads), return_inverse=True)[1]
    owner, cuts = np.repeat(np.arange(m), [len(h) for h in heads]), np.concatenate([[0], np.cumsum([len(h) for h in heads])])
    order = np.argsort(names, kind="stable")
    holders, runs = owner[order], np.concatenate([[0], np.cumsum(np.bincount(names))])
    trie = SetTrie(sets)
    place = np.empty(m, dtype=np.int64)
    place[trie.order] = np.arange(m)
    for a in trie.order[::-1] if sides is None else trie.order:
        probe = sets[a]
        if not len(probe):
            continue
        other = label[trie.order] != label[a]
        if sides is None:
            other[place[a] :] = False  # each pair once
        else:
            other &= sides[trie.order] != sides[a]
        other &= (100 * trie.sizes >= percent * len(probe)) & (percent * trie.sizes <= 100 * len(probe))
        if other.any():
            sharing = np.zeros(m, dtype=bool)
            for k in names[cuts[a] : cuts[a + 1]].tolist():
                if runs[k + 1] - runs[k] > 1:
                    sharing[holders[runs[k] : runs[k + 1]]] = True
            other &= sharing[trie.order]
        if other.any():
            hits = trie.order[trie.walk(probe, other, percent)]
            if len(hits):
                merged = np.unique(np.append(label[hits], label[a]))
                label[np.isin(label, merged)] = merged[0]
    return label


def _planes(values: np.ndarray) -> bytes:
    """Bytes of like weight side by side: sorted numbers then compress well in the shuffle."""
    return np.ascontiguousarray(values.view(np.uint8).reshape(len(values), -1).T).tobytes()


def _from_planes(data: bytes, dtype: type) -> np.ndarray:
    width = np.dtype(dtype).itemsize
    return np.ascontiguousarray(np.frombuffer(data, np.uint8).reshape(width, -1).T).view(dtype).reshape(-1)


def _home(block: int, buckets: int) -> int:
    """The bucket that a block's own rows pass through: blocks of all partitions spread evenly."""
    return (block * 0x9E3779B97F4A7C15 % (1 << 64)) >> (64 - int(buckets).bit_length() + 1)


_PARTS = pa.schema([("bucket", pa.int32()), ("block", pa.int64()), ("kind", pa.int32()), ("a", pa.binary()), ("b", pa.binary())])
_PART = "bucket int, block long, kind int, a binary, b binary"


def _shared_counts(docs: DataFrame, buckets: int, words: int) -> DataFrame:
    """(doc_id, n_shingles, n_shared, sig_hi, sig_lo): set size, shingles that other texts hold too, and
    a 128-bit signature of the set."""

    def deal(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        hashes, number, shift = WordHashes(), 0, np.uint64(64 - int(buckets).bit_length() + 1)
        for part in slices(batches, "text"):
            for low in range(0, part.num_rows, _MARK - 1):
                piece = part.slice(low, _MARK - 1)
                sets = [shingle_set(t, hashes, words) for t in text_bytes(piece.column("text"))]
                block, number = (TaskContext.get().partitionId() << 32) + number, number + 1
                sizes = np.array([len(s) for s in sets], dtype=np.int64)
                tokens, owner = np.concatenate(sets), np.repeat(np.arange(len(sets)), sizes)
                order = np.argsort(tokens, kind="stable")
                tokens, owner = tokens[order], owner[order]
                fresh = np.concatenate([[True], tokens[1:] != tokens[:-1]]) if len(tokens) else np.zeros(0, bool)
                at = np.flatnonzero(fresh)
                times = np.diff(np.append(at, len(tokens)))
                several = np.repeat(times > 1, times)
                here = np.bincount(owner[several], minlength=len(sets))
                signatures = [_signature(s) for s in sets]
                ids = piece.column("doc_id").cast(pa.int64())
                known = np.array([(i is not None, i or 0) for i in ids.to_pylist()], dtype=np.int64).reshape(-1, 2)
                head = np.concatenate([known, sizes[:, None], here[:, None], np.frombuffer(b"".join(signatures), np.int64).reshape(-1, 2)], axis=1)
                rows = [(_home(block, buckets), block, 1, head.astype(np.int64).tobytes(), b"")]
                token, mark = tokens[at], np.where(times > 1, _MARK, owner[at]).astype(np.uint16)
                bucket = (token >> shift).astype(np.int64)
                cuts = np.searchsorted(bucket, np.arange(buckets + 1))
                short = ((token << np.uint64(64 - int(shift))) >> np.uint64(32)).astype(np.uint32)
                for k in np.flatnonzero(np.diff(cuts)).tolist():
                    a, b = cuts[k], cuts[k + 1]
                    rows.append((k, block, 0, _planes(short[a:b]), _planes(mark[a:b])))
                yield pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip(zip(*rows, strict=True), _PARTS, strict=True)], schema=_PARTS)

    def count(table: pa.Table) -> pa.Table:
        out, parts = [], []
        for k in range(table.num_rows):
            if table["kind"][k].as_py() == 1:
                out.append((0, table["block"][k].as_py(), 1, table["a"][k].as_py(), b""))
            else:
                parts.append((table["block"][k].as_py(), _from_planes(table["a"][k].as_py(), np.uint32), _from_planes(table["b"][k].as_py(), np.uint16)))
        if parts:
            token, mark = np.concatenate([p[1] for p in parts]), np.concatenate([p[2] for p in parts])
            order = np.argsort(token, kind="stable")
            ordered = token[order]
            at = np.flatnonzero(np.concatenate([[True], ordered[1:] != ordered[:-1]]))
            times = np.diff(np.append(at, len(ordered)))
            shared = np.zeros(len(token), dtype=bool)
            shared[order] = np.repeat(times > 1, times)
            shared &= mark != _MARK
            low = 0
            for block, values, marks in parts:
                flags = shared[low : low + len(values)]
                low += len(values)
                if flags.any():
                    text, n = np.unique(marks[flags], return_counts=True)
                    out.append((0, block, 0, text.astype(np.uint16).tobytes(), n.astype(np.uint32).tobytes()))
        columns = list(zip(*out, strict=True)) or [[]] * 5
        return pa.table([pa.array(c, f.type) for c, f in zip(columns, _PARTS, strict=True)], schema=_PARTS)

    result = pa.schema([("doc_id", pa.int64()), ("n_shingles", pa.int64()), ("n_shared", pa.int64()), ("sig_hi", pa.int64()), ("sig_lo", pa.int64())])

    def collect(table: pa.Table) -> pa.Table:
        head, pairs = None, []
        for kind, a, b in zip(table["kind"].to_pylist(), table["a"].to_pylist(), table["b"].to_pylist(), strict=True):
            if kind == 1:
                head = np.frombuffer(a, np.int64).reshape(-1, 6)
            else:
                pairs.append((np.frombuffer(a, np.uint16), np.frombuffer(b, np.uint32)))
        total = head[:, 3].copy()
        for text, n in pairs:
            total[text] += n
        ids = pa.array(head[:, 1], pa.int64(), mask=head[:, 0] == 0)
        return pa.table([ids, *[pa.array(np.ascontiguousarray(x)) for x in (head[:, 2], total, head[:, 4], head[:, 5])]], schema=result)

    dealt = map_arrow(first_columns(docs, "doc_id", "text"), deal, _PART)
    counted = dealt.groupBy("bucket").applyInArrow(count, _PART)
    return counted.groupBy("block").applyInArrow(collect, "doc_id long, n_shingles long, n_shared long, sig_hi long, sig_lo long")


def _signature(shingles: np.ndarray) -> bytes:
    return hashlib.blake2b(shingles.tobytes(), digest_size=16).digest()


def _sets_of(docs: DataFrame, words: int) -> DataFrame:
    """(hi, lo, tokens): signature and shingles of each text."""
    schema = pa.schema([("hi", pa.int64()), ("lo", pa.int64()), ("tokens", pa.binary())])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        hashes = WordHashes()
        for part in slices(batches, "text"):
            sets = [shingle_set(t, hashes, words) for t in text_bytes(part.column("text"))]
            signs = np.frombuffer(b"".join(map(_signature, sets)), np.int64).reshape(-1, 2)
            columns = [pa.array(np.ascontiguousarray(x)) for x in signs.T]
            yield pa.RecordBatch.from_arrays([*columns, pa.array([x.tobytes() for x in sets], pa.binary())], schema=schema)

    return map_arrow(docs.select("text"), run, "hi long, lo long, tokens binary")


def _rare_first(sets: DataFrame, buckets: int) -> DataFrame:
    """(sid, tokens): the same sets under the global order of the join, rare shingles first.

    A shingle's place is its number of sets (up to 65535), then its hash, whole. The numbers of
    sets are counted over all sets, dealt out by hash; shingles whose hashes share 32 bits within
    a bucket are counted together, which moves them in the order and changes nothing else.
    """
    shift = np.uint64(64 - int(buckets).bit_length() + 1)

    def deal(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        number = 0
        for part in slices(batches, "tokens", 1 << 22):
            block, number = (TaskContext.get().partitionId() << 32) + number, number + 1
            raw = part.column("tokens").to_pylist()
            data = b"".join(raw)
            token, times = np.unique(np.frombuffer(data, np.uint64), return_counts=True)
            rows = [(_home(block, buckets), block, 1, data, np.array([part.column("sid").to_numpy(), [len(r) // 8 for r in raw]], dtype=np.int64).tobytes())]
            cuts = np.searchsorted(token >> shift, np.arange(buckets + 1).astype(np.uint64))
            short = ((token << np.uint64(64 - int(shift))) >> np.uint64(32)).astype(np.uint32)
            for k in np.flatnonzero(np.diff(cuts)).tolist():
                rows.append((k, block, 0, _planes(short[cuts[k] : cuts[k + 1]]), times[cuts[k] : cuts[k + 1]].astype(np.uint16).tobytes()))
            yield pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip(zip(*rows, strict=True), _PARTS, strict=True)], schema=_PARTS)

    def count(table: pa.Table) -> pa.Table:
        out, parts = [], []
        for bucket, block, kind, a, b in zip(*(table[c].to_pylist() for c in _PARTS.names), strict=True):
            if kind == 1:
                out.append((bucket, block, 1, a, b))
            else:
                parts.append((bucket, block, _from_planes(a, np.uint32), np.frombuffer(b, np.uint16)))
        if parts:
            names = np.unique(np.concatenate([p[2] for p in parts]), return_inverse=True)[1]
            total = np.bincount(names, weights=np.concatenate([p[3] for p in parts]).astype(np.float64))
            place = np.minimum(total, 0xFFFF).astype(np.uint16)[names]
            low = 0
            for bucket, block, short, _ in parts:
                out.append((bucket, block, 0, place[low : low + len(short)].tobytes(), b""))
                low += len(short)
        return pa.table([pa.array(c, f.type) for c, f in zip(zip(*out, strict=True), _PARTS, strict=True)], schema=_PARTS)

    def order(table: pa.Table) -> pa.Table:
        replies, head = {}, None
        for bucket, kind, a, b in zip(*(table[c].to_pylist() for c in ("bucket", "kind", "a", "b")), strict=True):
            if kind == 1:
                head = np.frombuffer(a, np.uint64), np.frombuffer(b, np.int64).reshape(2, -1)
            else:
                replies[bucket] = np.frombuffer(a, np.uint16)
        data, (sids, lengths) = head
        if not len(data):
            return pa.table({"sid": sids, "tokens": pa.array([b""] * len(sids), pa.binary())})
        token, at = np.unique(data, return_inverse=True)
        place = np.concatenate([replies[k] for k in sorted(replies)])
        ranked = data[np.lexsort((data, place[at], np.repeat(np.arange(len(sids)), lengths)))]
        cuts = np.cumsum(lengths)
        rows = [ranked[b - n : b].tobytes() for b, n in zip(cuts.tolist(), lengths.tolist(), strict=True)]
        return pa.table({"sid": sids, "tokens": pa.array(rows, pa.binary())})

    dealt = map_arrow(sets, deal, _PART).groupBy("bucket").applyInArrow(count, _PART)
    return dealt.groupBy("block").applyInArrow(order, "sid long, tokens binary")


def _prefix_rows(percent: int) -> Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]:
    """Rows (kind, a, b): 0 is a prefix shingle and a set that holds it, once per batch; 1 is a
    candidate link between sets of this batch."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for low in range(0, batch.num_rows, 2000):
                part = batch.slice(low, 2000)
                sets = [np.frombuffer(x, np.uint64) for x in part.column("tokens").to_pylist()]
                heads = [s[: len(s) + (-percent * len(s) // 100) + 1] for s in sets]
                owner = np.repeat(part.column("sid").to_numpy(), [len(h) for h in heads])
                token = np.concatenate(heads)
                order = np.lexsort((owner, token))
                token, owner = token[order], owner[order]
                fresh = np.concatenate([[True], token[1:] != token[:-1]]) if len(token) else np.zeros(0, bool)
                leader = owner[fresh][np.cumsum(fresh) - 1] if len(token) else owner
                u, v = local_stars(owner[~fresh], leader[~fresh])
                n = int(fresh.sum())
                yield pa.RecordBatch.from_arrays([pa.array(np.repeat([0, 1], [n, len(u)]).astype(np.int32)), pa.array(np.concatenate([token[fresh].view(np.int64), u])), pa.array(np.concatenate([owner[fresh], v]))], names=["kind", "a", "b"])

    return run


def _runs(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Links of each set to the first one with the same shingle, from rows sorted by shingle."""
    last, leader = None, None
    for batch in batches:
        token, owner = batch.column(0).to_numpy(), batch.column(1).to_numpy()
        if not len(token):
            continue
        fresh = np.concatenate([[last is None or token[0] != last], token[1:] != token[:-1]])
        group = np.cumsum(fresh) - 1
        leaders = np.concatenate([[leader if leader is not None else 0], owner[fresh]])[group + 1]
        last, leader = token[-1], leaders[-1]
        u, v = local_stars(owner[~fresh], leaders[~fresh])
        if len(u):
            yield pa.RecordBatch.from_arrays([pa.array(u), pa.array(v)], names=["u", "v"])


def block_rows(
    members: DataFrame,
    candidate: DataFrame,
    payload: str,
    block_sets: int = BLOCK_SETS,
    block_bytes: int = BLOCK_BYTES,
    broadcast_rows: int = 1_000_000,
) -> tuple[DataFrame, list[DataFrame]]:
    """(block, whole, sid, side, payload) of each member of a candidate component, sorted by block.

    A component of up to ``block_sets`` members and ``block_bytes`` of payload is one block. A
    larger one is dealt into chunks of about that, and each pair of chunks is a block, so that
    every pair of members meets in one. With it, the tables that it reads and nothing else does.
    """
    named = candidate.select("node", "root").union(candidate.select(F.col("root").alias("node"), "root")).distinct()
    named = materialise(named, "block-named")
    weighed = members.select(F.col("sid").alias("of"), F.octet_length(payload).alias("bytes"))
    sizes = weighed.join(named, F.col("of") == F.col("node")).groupBy("root").agg(F.count("*").alias("k"), F.sum("bytes").alias("bytes"))
    chunks = F.ceil(F.greatest(F.col("k") / F.lit(block_sets), F.col("bytes") / F.lit(block_bytes))).cast("int")
    sizes = materialise(sizes.select(F.col("root").alias("big"), chunks.alias("chunks")).where("chunks > 1"), "block-sizes")
    side = F.broadcast(sizes) if sizes.count() <= broadcast_rows else sizes
    joined = members.join(named, members["sid"] == named["node"]).join(side, F.col("root") == F.col("big"), "left")
    count = F.coalesce("chunks", F.lit(1))
    dealt = joined.withColumn("chunk", F.pmod(F.xxhash64("sid"), count).cast("int"))
    dealt = dealt.withColumn("other", F.explode(F.sequence(F.lit(0), count - 1)))
    block = F.xxhash64("root", F.least("chunk", "other"), F.greatest("chunk", "other"))
    rows = dealt.select(block.alias("block"), F.col("big").isNull().alias("whole"), "sid", F.col("chunk").alias("side"), payload)
    # a block's cost is in its pairs, not its bytes: tasks are not put together by bytes
    parts = int(members.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    return rows.repartition(parts, "block").sortWithinPartitions("block", "sid"), [named, sizes]


Block = tuple[np.ndarray | None, list[bytes]]


def joined_blocks(members: DataFrame, candidate: DataFrame, payload: str, solve: Callable[[list[Block]], list[np.ndarray]], block_sets: int = BLOCK_SETS, block_bytes: int = BLOCK_BYTES) -> DataFrame:
    """(node, root) of the members that are alike. ``solve`` maps blocks, each (sides or None,
    payloads), to the smallest member of each one's component. A whole component's answer stands;
    chunked ones are put together by their links."""

    def answers(blocks: list[tuple[list, list, list, bool]]) -> Iterator[pa.RecordBatch]:
        names = [np.array(ids, dtype=np.int64) for ids, _, _, _ in blocks]
        sides = [np.array(x) for _, x, _, _ in blocks]
        labels = solve([(None if (x == x[0]).all() else x, b[2]) for x, b in zip(sides, blocks, strict=True)])
        root = [n[label] for n, label in zip(names, labels, strict=True)]
        whole = np.repeat([b[3] for b in blocks], [len(n) for n in names])
        u, v = np.concatenate(names), np.concatenate(root)
        moved = u != v
        columns = [pa.array(x[moved]) for x in (u, v, whole)]
        yield pa.RecordBatch.from_arrays(columns, names=["u", "v", "whole"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[tuple[list, list, list, bool]] = []
        key, size = None, 0
        for batch in batches:
            for block, whole, sid, side, payload in zip(*(c.to_pylist() for c in batch.columns), strict=True):
                if block != key:
                    if size > SOLVE_BYTES:
                        yield from answers(held)
                        held, size = [], 0
                    held.append(([], [], [], whole))
                    key = block
                for column, x in zip(held[-1], (sid, side, payload)):
                    column.append(x)
                size += len(payload) + 64
        if held:
            yield from answers(held)

    rows, spent = block_rows(members, candidate, payload, block_sets, block_bytes)
    links = materialise(map_arrow(rows, run, "u long, v long, whole boolean"), "block-links")
    discard(*spent)
    done = links.where("whole").select(F.col("u").alias("node"), F.col("v").alias("root"))
    rest = links.where("not whole").select("u", "v")
    return done if rest.isEmpty() else done.unionByName(connected(rest))


def link_documents(docs: DataFrame, percent: int = PERCENT, words: int = WORDS, broadcast_rows: int = 1_000_000) -> DataFrame:
    """(doc_id, n_shingles, component_id) of each row.

    Rows link when 100 * overlap >= ``percent`` * union of their distinct ``words``-word shingles;
    ``component_id`` is the smallest doc_id reachable by links, itself included. Null, empty and
    blank texts have no shingles and link with nothing; rows with equal sets link with each other;
    rows of one doc_id with different texts are documents of their own; a null doc_id stays null
    and links nothing, and repeated rows are returned as often as they come; an empty table gives
    an empty result; other columns are ignored. Shingles are equal when their 64-bit hashes are,
    sets when their 128-bit signatures are.
    """
    spark = docs.sparkSession
    ship_package(spark)
    slim = first_columns(docs, "doc_id", "text")
    buckets = bucket_count(slim)
    table = materialise(_shared_counts(slim, buckets, words), "set-counts")
    able = table.where((100 * F.col("n_shared") >= percent * F.col("n_shingles")) & (F.col("n_shingles") > 0) & F.col("doc_id").isNotNull())
    # a number for each distinct set, whoever holds it, and the smallest of its documents
    leaders = able.groupBy("sig_hi", "sig_lo").agg(F.min("doc_id").alias("lead"))
    reps = materialise(leaders.withColumn("number", F.monotonically_increasing_id()), "set-leaders")
    near = F.broadcast if reps.count() <= broadcast_rows else lambda x: x
    wanted = reps.select("lead").distinct()
    chosen = _sets_of(slim.join(near(wanted), slim["doc_id"] == F.col("lead"), "left_semi"), words)
    same = (F.col("hi") == F.col("sig_hi")) & (F.col("lo") == F.col("sig_lo"))
    found = chosen.join(near(reps.select("sig_hi", "sig_lo", "number")), same)
    sets = materialise(found.select(F.col("number").alias("sid"), "tokens").dropDuplicates(["sid"]), "sets")
    ranked = materialise(_rare_first(sets, buckets), "ranked-sets")
    rows = materialise(map_arrow(ranked, _prefix_rows(percent), "kind int, a long, b long"), "prefixes")
    postings = rows.where("kind = 0").select("a", "b").repartition("a").sortWithinPartitions("a", "b")
    edges = map_arrow(postings, _runs, "u long, v long")
    candidate = connected(edges.union(rows.where("kind = 1").select(F.col("a").alias("u"), F.col("b").alias("v"))))

    def solve(blocks: list[Block]) -> list[np.ndarray]:
        return [similar_groups([np.frombuffer(x, np.uint64) for x in payloads], percent, sides) for sides, payloads in blocks]

    links = joined_blocks(ranked, candidate, "tokens", solve)
    grouped = reps.join(links, F.col("number") == F.col("node"), "left").withColumn("root", F.coalesce("root", "number"))
    grouped = materialise(grouped.select("sig_hi", "sig_lo", "lead", "root"), "set-roots")
    first = grouped.groupBy("root").agg(F.min("lead").alias("least"))
    named = grouped.join(first, "root").select(F.col("sig_hi").alias("hi"), F.col("sig_lo").alias("lo"), "least")
    named = materialise(named, "set-components")
    discard(sets, rows, ranked, candidate, reps, links, grouped)
    joined = table.join(named, same & (F.col("n_shingles") > 0), "left")
    least = F.coalesce(F.least("least", "doc_id"), F.col("doc_id"))
    return joined.select("doc_id", "n_shingles", F.when(F.col("doc_id").isNotNull(), least).alias("component_id"))
