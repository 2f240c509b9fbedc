"""Byte-level BPE by vectorised pre-tokenisation.

A text becomes an array of codepoint classes. A small machine reads one symbol per codepoint (its
class, and what stands right after it) and tells whether a piece begins there. Each symbol is a
function from states to states; such functions compose associatively, so their prefix
compositions come from a scan over many lanes at once, with no regular expression and no
per-character Python. The slices between boundaries go through a cache of merged pairs; those not
in it are merged many at a time, as rows of arrays. Byte offsets of the tokens follow from their
lengths, and decoding puts each token's bytes at its offset.
"""

from __future__ import annotations

import base64
import hashlib
import sys
import unicodedata
from collections.abc import Iterator
from dataclasses import dataclass
from functools import lru_cache
from heapq import heapify, heappop, heappush

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from .common import first_columns, map_arrow, slices

# Codepoint classes.
OTHER, LETTER, NUMBER, WHITE, BLANK, QUOTE = range(6)
# Input symbols of the machine: the classes, with look-ahead folded in.
S_OTHER, S_LETTER, S_NUMBER, S_WHITE_INNER, S_WHITE_LAST, S_BLANK_LAST, S_QUOTE1, S_QUOTE2 = range(8)
# States: what the codepoint just read belongs to.
Q_START, Q_OTHER, Q_LETTER, Q_NUMBER, Q_WHITE, Q_GLUE, Q_OWED1, Q_OWED2, Q_DONE = range(9)

#: Unicode White_Space codepoints.
WHITE_SPACE = [9, 10, 11, 12, 13, 32, 133, 160, 5760, 8192, 8193, 8194, 8195, 8196, 8197, 8198, 8199, 8200, 8201, 8202, 8232, 8233, 8239, 8287, 12288]

LANES = 2048
#: Pieces that the cache may hold when a slice begins; beyond, it starts anew.
CACHE_LIMIT = 200_000
#: Pieces of one length merged as one table, and the longest piece merged so.
MERGE_ROWS, LONG_PIECE = 20_000, 64
#: Text bytes encoded at once: their pieces are Python objects for a moment.
SLICE = 1 << 20


@lru_cache(maxsize=1)
def class_table() -> np.ndarray:
    """The class of every codepoint, from its Unicode general category."""
    kinds = {"L": LETTER, "N": NUMBER}
    table = np.fromiter((kinds.get(unicodedata.category(chr(c))[0], OTHER) for c in range(sys.maxunicode + 1)), np.uint8, sys.maxunicode + 1)
    table[WHITE_SPACE] = WHITE
    table[ord(" ")] = BLANK
    table[ord("'")] = QUOTE
    return table


def _step(state: int, symbol: int) -> tuple[int, bool]:
    """Next state, and whether a piece begins at the codepoint read."""
    if state in (Q_OWED1, Q_OWED2):  # letters of a contraction
        return (Q_DONE if state == Q_OWED1 else Q_OWED1), False
    glued = state == Q_GLUE
    if symbol in (S_QUOTE1, S_QUOTE2) and not glued and state != Q_OTHER:
        return (Q_OWED1 if symbol == S_QUOTE1 else Q_OWED2), True
    if symbol in (S_OTHER, S_QUOTE1, S_QUOTE2):
        return Q_OTHER, not (glued or state == Q_OTHER)
    if symbol == S_LETTER:
        return Q_LETTER, not (glued or state == Q_LETTER)
    if symbol == S_NUMBER:
        return Q_NUMBER, not (glued or state == Q_NUMBER)
    if symbol == S_WHITE_INNER:  # the next codepoint is white space too, or the text ends
        return Q_WHITE, state != Q_WHITE
    return (Q_GLUE if symbol == S_BLANK_LAST else Q_DONE), True  # the last one before other text stands apart


@lru_cache(maxsize=1)
def machine() -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """(function of each symbol, composition table, functions' results, begins[state, symbol]).

    The functions are closed under composition first, so one small integer stands for each.
    """
    states, symbols = range(9), range(8)
    basic = [tuple(_step(q, s)[0] for q in states) for s in symbols]
    known = {f: i for i, f in enumerate(dict.fromkeys([tuple(states), *basic]))}
    queue = list(known)
    for f in queue:
        for g in basic:
            h = tuple(g[q] for q in f)
            if h not in known:
                known[h] = len(known)
                queue.append(h)
    functions = np.array(list(known), dtype=np.uint8)
    then = np.array([[known[tuple(g[q] for q in f)] for g in known] for f in known], dtype=np.uint16)
    begins = np.array([[_step(q, s)[1] for s in symbols] for q in states])
    return np.array([known[f] for f in basic], dtype=np.uint16), then, functions, begins


def symbols_of(codes: np.ndarray, ends: np.ndarray) -> np.ndarray:
    """Input symbols; ``ends`` marks the last codepoint of each text."""
    classes = class_table()[codes]
    space = (classes == WHITE) | (classes == BLANK)
    last = np.zeros(len(codes), dtype=bool)
    last[:-1] = space[:-1] & ~space[1:]
    last &= ~ends
    out = np.array([S_OTHER, S_LETTER, S_NUMBER, S_WHITE_INNER, S_WHITE_INNER, S_OTHER], dtype=np.uint8)[classes]
    out[last] = np.where(classes[last] == BLANK, S_BLANK_LAST, S_WHITE_LAST)
    quotes = np.flatnonzero(classes == QUOTE)
    if len(quotes):
        ahead = np.concatenate([codes, np.zeros(2, codes.dtype)])
        stop = np.concatenate([ends, np.ones(2, bool)])
        one, two = ahead[quotes + 1], ahead[quotes + 2]
        has1 = ~stop[quotes]
        has2 = has1 & ~stop[quotes + 1]
        short = has1 & np.isin(one, [ord(c) for c in "stmd"])
        long = has2 & (((one == ord("r")) & (two == ord("e"))) | ((one == ord("v")) & (two == ord("e"))) | ((one == ord("l")) & (two == ord("l"))))
        out[quotes[short]] = S_QUOTE1
        out[quotes[long]] = S_QUOTE2
    return out


def piece_starts(codes: np.ndarray, ends: np.ndarray, lanes: int = LANES) -> np.ndarray:
    """Whether a piece begins at each codepoint of the texts laid end to end."""
    n = len(codes)
    if not n:
        return np.zeros(0, dtype=bool)
    basic, then, functions, begins = machine()
    symbols = symbols_of(codes, ends)
    own = basic[symbols]
    first = np.concatenate([[True], ends[:-1]])
    steps = -(-n // lanes)
    padded = np.zeros(steps * lanes, dtype=np.uint16)  # 0 is the identity
    padded[:n] = own
    restart = np.zeros(steps * lanes, dtype=bool)
    restart[:n] = first
    grid, restarts = padded.reshape(lanes, steps).T.copy(), restart.reshape(lanes, steps).T.copy()
    # A text's first codepoint begins from the start state whatever was read before it: the
    # constant function with that result, looked up among the known ones or kept as a mask.
    prefix = np.empty_like(grid)  # composition of all before this place in its lane
    base = np.zeros(lanes, dtype=np.int64)  # 0: still depends on the lane's first state
    fixed = np.empty((steps, lanes), dtype=bool)
    current = np.zeros(lanes, dtype=np.uint16)
    for t in range(steps):
        fresh = restarts[t]
        if fresh.any():
            current = np.where(fresh, 0, current).astype(np.uint16)
            base = np.where(fresh, 1, base)
        prefix[t], fixed[t] = current, base == 1
        current = then[current, grid[t]]
    # Carry the state over the lanes; a lane with a restart inside does not pass its first state on.
    carried, state = np.empty(lanes, dtype=np.uint8), Q_START
    for lane in range(lanes):
        carried[lane] = state
        state = functions[current[lane], Q_START if base[lane] else state]
    entering = functions[prefix, np.where(fixed, Q_START, carried[None, :])]
    before = entering.T.reshape(-1)[:n]
    return begins[before, symbols] | first


NONE = np.int64(1 << 40)  # in place of a rank: the pair is in no token


def spans(starts: np.ndarray, lengths: np.ndarray) -> np.ndarray:
    """The places of runs of ``lengths`` from ``starts``, one run after the other."""
    stops = np.cumsum(lengths)
    return np.repeat(starts - (stops - lengths), lengths) + np.arange(int(stops[-1]) if len(stops) else 0)


class PairTable:
    """Open-addressing table from a pair of token ids to the id of the token they join to."""

    def __init__(self, ranks: dict[bytes, int]):
        found = []
        for token, rank in ranks.items():
            for cut in range(1, len(token)):
                left = ranks.get(token[:cut])
                right = ranks.get(token[cut:]) if left is not None else None
                if right is not None:
                    found.append((left, right, rank))
        pairs = np.array(found, dtype=np.int64).reshape(-1, 3)
        self.base = np.int64(max(ranks.values(), default=0) + 2)  # base - 1 is no token's id
        bits = max(4, int(4 * len(pairs)).bit_length())
        self.shift, self.mask = np.uint64(64 - bits), np.int64((1 << bits) - 1)
        self.keys = np.full(1 << bits, -1, dtype=np.int64)
        self.values = np.full(1 << bits, NONE, dtype=np.int64)
        keys, values = pairs[:, 0] * self.base + pairs[:, 1], pairs[:, 2]
        at = self._home(keys)
        while len(keys):
            free = self.keys[at] < 0
            slot, first = np.unique(at[free], return_index=True)
            settled = np.flatnonzero(free)[first]
            self.keys[slot], self.values[slot] = keys[settled], values[settled]
            left = np.ones(len(keys), dtype=bool)
            left[settled] = False
            keys, values, at = keys[left], values[left], (at[left] + 1) & self.mask

    def _home(self, keys: np.ndarray) -> np.ndarray:
        with np.errstate(over="ignore"):
            return ((keys.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15)) >> self.shift).astype(np.int64)

    def join(self, left: np.ndarray, right: np.ndarray) -> np.ndarray:
        """Id (and so rank) of the token that each pair joins to, NONE where there is none."""
        keys = (left * self.base + right).reshape(-1)
        at = self._home(keys)
        held, out = self.keys[at], self.values[at]
        open_ = np.flatnonzero((held != keys) & (held >= 0))
        out[held != keys] = NONE
        while len(open_):
            at[open_] = (at[open_] + 1) & self.mask
            held = self.keys[at[open_]]
            hit = held == keys[open_]
            out[open_[hit]] = self.values[at[open_[hit]]]
            open_ = open_[~hit & (held >= 0)]
        return out.reshape(np.shape(left))


@dataclass(frozen=True)
class Tokenizer:
    """A rank file in the forms that encoding and decoding read."""

    ranks: dict[bytes, int]
    pairs: PairTable
    byte_ids: np.ndarray
    text: np.ndarray  # bytes of all tokens, by id
    text_at: np.ndarray
    decimal: np.ndarray  # decimal ids, each with a blank after it
    decimal_at: np.ndarray


@lru_cache(maxsize=4)
def load(path: str) -> Tokenizer:
    with open(path, "rb") as lines:
        ranks = {base64.b64decode(a): int(b) for a, b in map(bytes.split, lines)}
    count = max(ranks.values(), default=-1) + 1
    tokens = [b""] * count
    for token, rank in ranks.items():
        tokens[rank] = token
    numbers = [b"%d " % i for i in range(count)]
    joined = [np.frombuffer(b"".join(x), dtype=np.uint8) for x in (tokens, numbers)]
    cuts = [np.concatenate([[0], np.cumsum([len(t) for t in x], dtype=np.int64)]) for x in (tokens, numbers)]
    byte_ids = np.array([ranks.get(bytes([b]), -1) for b in range(256)], dtype=np.int64)
    return Tokenizer(ranks, PairTable(ranks), byte_ids, joined[0], cuts[0], joined[1], cuts[1])


def load_ranks(path: str) -> dict[bytes, int]:
    return load(path).ranks


class Codec:
    """Encoder and decoder over one rank file.

    The cache names a place in ``ids`` for each piece met. Pieces that are not in it yet are
    merged together, all pieces of a length as the rows of one table.
    """

    def __init__(self, path: str):
        self.model = load(path)
        self.ranks = self.model.ranks
        self.forget()

    def forget(self) -> None:
        self.cache: dict[bytes, int] = {}
        self.ids = np.zeros(0, dtype=np.int64)
        self.cuts = np.zeros(1, dtype=np.int64)

    def learn(self, pieces: list[bytes]) -> None:
        """Put the ids of these pieces, none of which it holds, into the cache."""
        groups: dict[int, list[bytes]] = {}
        for piece in pieces:
            groups.setdefault(0 if piece in self.ranks else len(piece), []).append(piece)
        order, ids, counts = [], [self.ids], []
        for length, group in groups.items():
            if length == 0:
                found = np.fromiter(map(self.ranks.__getitem__, group), np.int64, len(group))
                ids.append(found)
                counts.append(np.ones(len(group), dtype=np.int64))
            elif length > LONG_PIECE:
                lists = [self.merge_long(piece) for piece in group]
                ids += [np.array(x, dtype=np.int64) for x in lists]
                counts.append(np.array([len(x) for x in lists], dtype=np.int64))
            else:
                for low in range(0, len(group), MERGE_ROWS):
                    found, count = self.merge_rows(b"".join(group[low : low + MERGE_ROWS]), length)
                    ids.append(found)
                    counts.append(count)
            order += group
        held = len(self.cache)
        self.cache.update(zip(order, range(held, held + len(order)), strict=True))
        self.ids = np.concatenate(ids)
        self.cuts = np.concatenate([self.cuts, self.cuts[-1] + np.cumsum(np.concatenate(counts))])

    def merge_rows(self, data: bytes, length: int) -> tuple[np.ndarray, np.ndarray]:
        """(ids, ids of each piece) of pieces of one length laid end to end. In each round every
        piece joins its adjacent pair of lowest rank, the leftmost of equals, until none has one."""
        join = self.model.pairs.join
        none = int(self.model.pairs.base) - 1
        table = self.model.byte_ids[np.frombuffer(data, dtype=np.uint8).reshape(-1, length)]
        count = len(table)
        ids = np.concatenate([table, np.full((count, 1), none)], axis=1)  # the last column stands for both ends
        rank = np.full((count, length + 1), NONE)
        rank[:, : length - 1] = join(table[:, :-1], table[:, 1:])
        after = np.tile(np.append(np.arange(1, length + 1), length), (count, 1))
        before = np.tile(np.append(np.append(length, np.arange(length - 1)), length), (count, 1))
        there = np.ones((count, length), dtype=bool)
        rows = np.arange(count)
        while len(rows):
            at = rank[rows].argmin(axis=1)
            lowest = rank[rows, at]
            some = lowest < NONE
            rows, at, lowest = rows[some], at[some], lowest[some]
            eaten = after[rows, at]
            follower, leader = after[rows, eaten], before[rows, at]
            there[rows, eaten] = False
            ids[rows, at] = lowest
            after[rows, at], before[rows, follower] = follower, at
            rank[rows, eaten] = NONE
            rank[rows, at] = join(lowest, ids[rows, follower])
            rank[rows, leader] = join(ids[rows, leader], lowest)
        return ids[:, :length][there], there.sum(axis=1)

    def merge_long(self, piece: bytes) -> list[int]:
        """The same for one piece of any length, with a heap and linked neighbours."""
        ranks, n = self.ranks, len(piece)
        end = list(range(1, n + 1))
        after, before = list(range(1, n + 1)), list(range(-1, n - 1))
        alive = [True] * n

        def rank(i: int) -> int | None:
            j = after[i]
            return ranks.get(piece[i : end[j]]) if j < n else None

        heap = [(r, i, end[i + 1]) for i in range(n - 1) if (r := rank(i)) is not None]
        heapify(heap)
        while heap:
            r, i, stop = heappop(heap)
            if not alive[i] or after[i] >= n or end[after[i]] != stop or rank(i) != r:
                continue
            j = after[i]
            alive[j], end[i], after[i] = False, end[j], after[j]
            if after[i] < n:
                before[after[i]] = i
            for k in (i, before[i]):
                if k >= 0 and (q := rank(k)) is not None:
                    heappush(heap, (q, k, end[after[k]]))
        out, i = [], 0
        while i < n:
            out.append(ranks[piece[i : end[i]]])
            i = after[i]
        return out

    def merge(self, piece: bytes) -> tuple[int, ...]:
        """Ids of one piece."""
        if piece not in self.cache:
            self.learn([piece])
        slot = self.cache[piece]
        return tuple(self.ids[self.cuts[slot] : self.cuts[slot + 1]].tolist())

    def split(self, texts: list[str]) -> tuple[list[bytes], np.ndarray]:
        """Pieces of the texts as bytes, and where each text's pieces begin among them."""
        joined = "".join(texts)
        codes = np.frombuffer(joined.encode("utf-32-le", "surrogatepass"), dtype=np.uint32).astype(np.int32)
        lengths = np.fromiter(map(len, texts), np.int64, len(texts))
        stops = np.cumsum(lengths)
        ends = np.zeros(len(codes), dtype=bool)
        ends[stops[lengths > 0] - 1] = True
        starts = piece_starts(codes, ends)
        width = 1 + (codes > 0x7F).astype(np.int8) + (codes > 0x7FF) + (codes > 0xFFFF)
        at = np.concatenate([[0], np.cumsum(width, dtype=np.int64)])
        begin = np.flatnonzero(starts)
        cuts = [*at[begin].tolist(), int(at[-1])]
        data = joined.encode("utf-8", "surrogatepass")
        pieces = [data[a:b] for a, b in zip(cuts, cuts[1:])]
        return pieces, np.searchsorted(begin, np.concatenate([[0], stops]), "left")

    def encode(self, texts: list[str]) -> tuple[np.ndarray, np.ndarray]:
        """Ids of all texts laid end to end, and where each text's ids begin among them."""
        pieces, owner = self.split(texts)
        if len(self.cache) > CACHE_LIMIT:
            self.forget()
        if fresh := set(pieces).difference(self.cache):
            self.learn(list(fresh))
        slots = np.fromiter(map(self.cache.__getitem__, pieces), np.int64, len(pieces))
        counts = self.cuts[slots + 1] - self.cuts[slots]
        ids = self.ids[spans(self.cuts[slots], counts)]
        return ids, np.concatenate([[0], np.cumsum(counts)])[owner]

    def offsets(self, ids: np.ndarray, cuts: np.ndarray) -> np.ndarray:
        """Byte offset at which each token begins in its own text."""
        stops = self.model.text_at[ids + 1] - self.model.text_at[ids]
        begin = np.concatenate([[0], np.cumsum(stops)])
        return begin[:-1] - np.repeat(begin[cuts[:-1]], np.diff(cuts))

    def decode(self, ids: np.ndarray, cuts: np.ndarray, offsets: np.ndarray) -> list[bytes]:
        """Bytes of each text: every token's bytes put at its offset."""
        sizes = self.model.text_at[ids + 1] - self.model.text_at[ids]
        ends = np.append(offsets + sizes, 0)  # a text is as long as its last token's end
        last = cuts[1:] - 1
        total = np.where(np.diff(cuts) > 0, ends[last], 0)
        starts = np.concatenate([[0], np.cumsum(total)])
        out = np.zeros(int(starts[-1]), dtype=np.uint8)
        out[spans(offsets + np.repeat(starts[:-1], np.diff(cuts)), sizes)] = self.model.text[spans(self.model.text_at[ids], sizes)]
        data = out.tobytes()
        return [data[a:b] for a, b in zip(starts.tolist(), starts[1:].tolist())]

    def decimals(self, ids: np.ndarray, cuts: np.ndarray) -> list[bytes]:
        """Decimal ids of each text, joined by one blank."""
        sizes = self.model.decimal_at[ids + 1] - self.model.decimal_at[ids]
        data = self.model.decimal[spans(self.model.decimal_at[ids], sizes)].tobytes()
        at = np.concatenate([[0], np.cumsum(sizes)])[cuts].tolist()
        return [data[a : max(a, b - 1)] for a, b in zip(at, at[1:])]


_codecs: dict[str, Codec] = {}


def codec(path: str) -> Codec:
    """One codec, and so one cache, per Python worker and rank file."""
    if path not in _codecs:
        _codecs[path] = Codec(path)
    return _codecs[path]


def encode_documents(docs: DataFrame, ranks_path: str) -> DataFrame:
    """(doc_id, n_tokens, tokens array<int>, token_offsets array<int>) of each whole text.

    Null or empty text has no tokens; offsets are byte offsets into the text's UTF-8. The rank
    file must be readable at ``ranks_path`` on each executor. Other columns are ignored.
    """
    ints = pa.list_(pa.int32())
    schema = pa.schema([("doc_id", pa.int64()), ("n_tokens", pa.int64()), ("tokens", ints), ("token_offsets", ints)])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        coder = codec(ranks_path)
        for part in slices(batches, "text", SLICE):
            ids, cuts = coder.encode([t or "" for t in part.column("text").to_pylist()])
            edges = pa.array(cuts, pa.int32())
            lists = [pa.ListArray.from_arrays(edges, pa.array(x, pa.int32())) for x in (ids, coder.offsets(ids, cuts))]
            counts = pa.array(np.diff(cuts), pa.int64())
            yield pa.RecordBatch.from_arrays([part.column("doc_id").cast(pa.int64()), counts, *lists], schema=schema)

    return map_arrow(first_columns(docs, "doc_id", "text"), run, "doc_id long, n_tokens long, tokens array<int>, token_offsets array<int>")


def token_digests(docs: DataFrame, ranks_path: str) -> DataFrame:
    """(doc_id, n_tokens, ids_sha256, decoded_sha256, last_offset): encoding, and decoding of its
    ids at their offsets, digested where they are made. ``last_offset`` is the byte at which the
    last token begins. Null text counts as empty: no tokens, digests of nothing, null offset."""
    kinds = "doc_id long, n_tokens long, ids_sha256 string, decoded_sha256 string, last_offset long"
    schema = pa.schema([("doc_id", pa.int64()), ("n_tokens", pa.int64()), ("ids_sha256", pa.string()), ("decoded_sha256", pa.string()), ("last_offset", pa.int64())])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        coder = codec(ranks_path)
        sha = hashlib.sha256
        for part in slices(batches, "text", SLICE):
            ids, cuts = coder.encode([t or "" for t in part.column("text").to_pylist()])
            offsets, counts = coder.offsets(ids, cuts), np.diff(cuts)
            written = [sha(x).hexdigest() for x in coder.decimals(ids, cuts)]
            decoded = [sha(x).hexdigest() for x in coder.decode(ids, cuts, offsets)]
            last = pa.array(np.append(offsets, 0)[cuts[1:] - 1], pa.int64(), mask=counts == 0)
            yield pa.RecordBatch.from_arrays([part.column("doc_id").cast(pa.int64()), pa.array(counts), pa.array(written), pa.array(decoded), last], schema=schema)

    return map_arrow(first_columns(docs, "doc_id", "text"), run, kinds)


def decode_documents(encoded: DataFrame, ranks_path: str) -> DataFrame:
    """(doc_id, text) from (doc_id, tokens); null tokens give an empty text."""
    schema = pa.schema([("doc_id", pa.int64()), ("text", pa.string())])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        coder = codec(ranks_path)
        for part in batches:
            lists = [x or [] for x in part.column("tokens").to_pylist()]
            ids = np.array([i for x in lists for i in x], dtype=np.int64)
            cuts = np.concatenate([[0], np.cumsum([len(x) for x in lists], dtype=np.int64)])
            texts = [x.decode("utf-8", "replace") for x in coder.decode(ids, cuts, coder.offsets(ids, cuts))]
            yield pa.RecordBatch.from_arrays([part.column("doc_id").cast(pa.int64()), pa.array(texts, pa.string())], schema=schema)

    return map_arrow(first_columns(encoded, "doc_id", "tokens"), run, "doc_id long, text string")
