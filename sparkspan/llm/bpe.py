"""Byte-level BPE encoding and decoding with array-wise pre-tokenisation.

A batch of texts is one array of code points. Lookup tables turn it into an array of symbols: the class of
each code point, with what has to be known of the next ones. A small machine reads the symbols; its state
says which kind of piece is open. Every symbol stands for a transition function, from the state before
to the state after it; such functions compose associatively, and all compositions that can arise (some
dozens) are numbered once, with a table of their products. The state at every place is then a prefix scan
over that table, done block by block for all blocks at once, and a piece starts where state and symbol
say so. No regular expression runs. The slices feed a cache of merged pieces; their offsets stay with the
ids, so that any run of tokens decodes by itself.
"""

from __future__ import annotations

import base64
import hashlib
import sys
import unicodedata
from collections.abc import Iterable, Iterator
from dataclasses import dataclass
from functools import cache
from itertools import chain

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import column

OTHER, LETTER, NUMBER, SPACE = 0, 1, 2, 3
#: Code points of white space, and the endings split off after an apostrophe.
WHITE = [*range(9, 14), 32, 0x85, 0xA0, 0x1680, *range(0x2000, 0x200B), 0x2028, 0x2029, 0x202F, 0x205F, 0x3000]
ENDINGS = ("s", "t", "re", "ve", "m", "ll", "d")
#: Pieces that the cache holds before it starts anew, and code points handled at once.
CACHE, BLOCK = 1 << 18, 1 << 19


@cache
def classes() -> np.ndarray:
    out = np.zeros(sys.maxunicode + 1, np.uint8)
    kinds = {"L": LETTER, "N": NUMBER}
    out[:] = [kinds.get(unicodedata.category(chr(c))[0], OTHER) for c in range(sys.maxunicode + 1)]
    out[WHITE] = SPACE
    return out


#: States: the open piece is closed for good, or is of other marks, letters, numbers or white space, or is one
#: blank that joins what follows, or lacks one or two more letters of an ending.
CLOSED, MARKS, LETTERS, NUMBERS, WHITES, BLANK, ONE, TWO = range(8)
STATES = 8
#: Symbols beyond the classes: white space that is the last before something else, which is a plain blank or is
#: not; an apostrophe with an ending of one or of two letters behind it. HEAD is added where a text starts.
LAST_BLANK, LAST_WHITE, ENDING1, ENDING2, HEAD = 4, 5, 6, 7, 8


def step(state: int, symbol: int) -> tuple[bool, int]:
    """(a piece starts here, next state) of the machine."""
    if symbol >= HEAD:
        state, symbol = CLOSED, symbol - HEAD
    if state in (ONE, TWO):  # letters of an ending
        return False, CLOSED if state == ONE else ONE
    if symbol in (LETTER, NUMBER, OTHER):
        own = {LETTER: LETTERS, NUMBER: NUMBERS, OTHER: MARKS}[symbol]
        return state not in (own, BLANK), own
    if symbol in (ENDING1, ENDING2):  # within marks or behind a blank it is a mark like others
        return state not in (MARKS, BLANK), MARKS if state in (MARKS, BLANK) else ONE if symbol == ENDING1 else TWO
    if symbol == SPACE:
        return state != WHITES, WHITES
    return True, BLANK if symbol == LAST_BLANK else CLOSED


@cache
def machine() -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """(number of each symbol's function, products, results, starts): ``products[f, g]`` numbers g after f,
    ``results[f]`` is the state f leads to from CLOSED, ``starts[state, symbol]`` tells a piece's start.
    Number 0 is the function that changes nothing. Found by closing the symbols' functions under composition."""
    symbols = [tuple(step(s, x)[1] for s in range(STATES)) for x in range(2 * HEAD)]
    same = tuple(range(STATES))
    after = lambda f, g: tuple(g[s] for s in f)
    number, todo = {same: 0}, [same]
    while todo:
        f = todo.pop()
        for g in symbols:
            if (h := after(f, g)) not in number:
                number[h] = len(number)
                todo.append(h)
    found = list(number)
    products = np.array([[number[after(f, g)] for g in found] for f in found], np.uint8 if len(found) <= 256 else np.uint16)
    starts = np.array([[step(s, x)[0] for x in range(2 * HEAD)] for s in range(STATES)])
    return np.array([number[f] for f in symbols], products.dtype), products, np.array([f[CLOSED] for f in found], np.uint8), starts


def scan(functions: np.ndarray, products: np.ndarray) -> np.ndarray:
    """Composition of all functions up to each place, itself included. Runs of some hundred places go on side by
    side, one place of every run a step; what the runs before them come to is a scan over their ends."""
    n = len(functions)
    if n <= 32:
        out = functions.copy()
        for i in range(1, n):
            out[i] = products[out[i - 1], out[i]]
        return out
    width = max(8, min(512, int(n**0.5)))
    runs = -(-n // width)
    padded = np.zeros(runs * width, functions.dtype)
    padded[:n] = functions
    part = np.ascontiguousarray(padded.reshape(runs, width).T)
    for i in range(1, width):
        part[i] = products[part[i - 1], part[i]]
    before = np.zeros(runs, functions.dtype)
    before[1:] = scan(part[-1, :-1], products)
    return products[before[None, :], part].T.reshape(-1)[:n]


def symbols(cp: np.ndarray, head: np.ndarray) -> np.ndarray:
    """The symbol at each place. head: a text starts there; one place more than ``cp``, for the end."""
    n = len(cp)
    out = classes()[cp]
    space = out == SPACE
    last = np.flatnonzero(space[:-1] & ~space[1:] & ~head[1:n])
    mark = np.flatnonzero(cp == 39)
    mark = mark[mark + 1 < n]
    mark = mark[~head[mark + 1]]
    after = np.append(cp, np.zeros(2, np.uint32))
    whole = ~head[np.minimum(mark + 2, n)]
    for ending in ENDINGS:
        hit = after[mark + 1] == ord(ending[0])
        if len(ending) == 2:
            hit &= (after[mark + 2] == ord(ending[1])) & whole
        out[mark[hit]] = ENDING1 if len(ending) == 1 else ENDING2
    out[last] = np.where(cp[last] == 32, LAST_BLANK, LAST_WHITE)
    return out + HEAD * head[:n].astype(np.uint8)


def boundaries(text: str, starts: np.ndarray | None = None) -> np.ndarray:
    """Start offsets of the pieces of ``text``, in order. ``starts``: first offsets of the texts that
    ``text`` joins, when it holds more than one; pieces never cross them."""
    n = len(text)
    if not n:
        return np.zeros(0, np.int64)
    cp = np.frombuffer(text.encode("utf-32-le", "surrogatepass"), np.uint32)
    head = np.zeros(n + 1, bool)  # a text starts here, or has ended
    head[[0, n]] = True
    if starts is not None:
        head[starts] = True
    numbers, products, results, begins = machine()
    read = symbols(cp, head)
    state = np.empty(n, np.uint8)
    state[0] = CLOSED
    state[1:] = results[scan(numbers[read[:-1]], products)]
    return np.flatnonzero(begins[state, read])


@dataclass
class Encoded:
    """Tokens of a text, with the offsets of the pieces that they come from: ``starts`` are places of code
    points, ``upto`` how many tokens the pieces up to and including each one have."""

    ids: list[int]
    starts: np.ndarray
    upto: np.ndarray

    def piece_of(self, token: int) -> int:
        return int(np.searchsorted(self.upto, token, "right"))

    def span(self, first: int, last: int) -> tuple[int, int]:
        """Tokens ``a .. b - 1`` of the pieces from that which starts at or before code point ``first`` to that
        which ends at or behind ``last``: what to decode for this part of the text."""
        p, q = max(0, int(np.searchsorted(self.starts, first, "right")) - 1), int(np.searchsorted(self.starts, last, "left"))
        return (int(self.upto[p - 1]) if p else 0), (int(self.upto[q - 1]) if q else 0)


class Codec:
    """Encoder and decoder over a rank table {bytes: id}."""

    def __init__(self, ranks: dict[bytes, int]):
        self.ranks, self.bytes = ranks, {i: b for b, i in ranks.items()}
        self.known: dict[str, tuple[int, ...]] = {}

    def merge(self, piece: bytes) -> tuple[int, ...]:
        """Ids of one piece: the adjacent pair of least rank, the leftmost among equals, merges first."""
        if (i := self.ranks.get(piece)) is not None:
            return (i,)
        ranks, none = self.ranks, 1 << 60
        if len(piece) > 200:
            return self._merge_long(piece)
        parts = [piece[i : i + 1] for i in range(len(piece))]
        pair = [ranks.get(parts[i] + parts[i + 1], none) for i in range(len(parts) - 1)]
        while pair:
            i = pair.index(least := min(pair))
            if least == none:
                break
            parts[i : i + 2] = [parts[i] + parts[i + 1]]
            del pair[i]
            if i < len(pair):
                pair[i] = ranks.get(parts[i] + parts[i + 1], none)
            if i:
                pair[i - 1] = ranks.get(parts[i - 1] + parts[i], none)
        return tuple(ranks[p] for p in parts)

    def _merge_long(self, piece: bytes) -> tuple[int, ...]:
        """The same with a heap and links, for pieces of any length."""
        from heapq import heapify, heappop, heappush

        n, ranks = len(piece), self.ranks
        end, prev = list(range(1, n + 1)), list(range(-1, n - 1))
        alive = [True] * n
        rank = lambda i: ranks.get(piece[i : end[end[i]]]) if end[i] < n else None
        heap = [(r, i, end[i + 1]) for i in range(n - 1) if (r := rank(i)) is not None]
        heapify(heap)
        while heap:
            _, i, to = heappop(heap)
            if not alive[i] or end[i] >= n or end[end[i]] != to:
                continue
            j = end[i]
            alive[j], end[i] = False, end[j]
            if end[i] < n:
                prev[end[i]] = i
            for k in (i, prev[i]):
                if k >= 0 and (r := rank(k)) is not None:
                    heappush(heap, (r, k, end[end[k]]))
        return tuple(ranks[piece[i : end[i]]] for i in range(n) if alive[i])

    def _ids(self, pieces: list[str]) -> list[tuple[int, ...]]:
        known = self.known
        if len(known) > CACHE:
            known.clear()
        for p in set(pieces).difference(known):
            known[p] = self.merge(p.encode("utf-8", "surrogatepass"))
        return list(map(known.__getitem__, pieces))

    def encode_batch(self, texts: list[str]) -> Iterator[Encoded]:
        """Texts are joined up to BLOCK code points; a longer one is alone."""
        group: list[str] = []
        held = 0
        for t in texts:
            if group and held + len(t) > BLOCK:
                yield from self._joined(group)
                group, held = [], 0
            group.append(t)
            held += len(t)
        if group:
            yield from self._joined(group)

    def _joined(self, group: list[str]) -> Iterator[Encoded]:
        sizes = np.array([len(t) for t in group])
        firsts = np.cumsum(sizes) - sizes
        whole = "".join(group)
        cuts = boundaries(whole, firsts[firsts < len(whole)])
        at = np.searchsorted(cuts, firsts).tolist()
        edges = [*cuts.tolist(), len(whole)]
        for k, n in enumerate(sizes.tolist()):
            if not n:
                yield Encoded([], np.zeros(0, np.int64), np.zeros(0, np.int64))
                continue
            a, b = at[k], at[k + 1] if k + 1 < len(at) else len(edges) - 1
            ids: list[int] = []
            counts: list[int] = []
            for j in range(a, b, 1 << 16):
                part = edges[j : min(b, j + (1 << 16)) + 1]
                found = self._ids([whole[x:y] for x, y in zip(part, part[1:])])
                ids += chain.from_iterable(found)
                counts += map(len, found)
            yield Encoded(ids, cuts[a:b] - firsts[k], np.cumsum(counts))

    def decode(self, ids: Iterable[int]) -> bytes:
        return b"".join(map(self.bytes.__getitem__, ids))

    def decode_part(self, e: Encoded, first: int, last: int) -> tuple[int, str]:
        """(code point at which it starts, text) of the pieces that cover code points first .. last - 1, by
        decoding their tokens only."""
        a, b = e.span(first, last)
        p = e.piece_of(a) if a < len(e.ids) else len(e.starts)
        return (int(e.starts[p]) if p < len(e.starts) else first), self.decode(e.ids[a:b]).decode("utf-8", "surrogatepass")


def load_ranks(path: str) -> dict[bytes, int]:
    with open(path, "rb") as f:
        return {base64.b64decode(a): int(b) for a, b in (line.split() for line in f if line.strip())}


def load_table(path: str) -> dict[bytes, int]:
    """The ranks, whose number a vocabulary bounds; raises beyond what may be sent to every executor."""
    ranks = load_ranks(path)
    if len(ranks) > 1 << 20:
        raise ValueError("rank table too large to send to every executor")
    return ranks


def encode(df: DataFrame, ranks_path: str, id_col: str = "doc_id", text_col: str = "text", with_ids: bool = False, with_offsets: bool = False) -> DataFrame:
    """One row per document: id, n_tokens, ids_sha256, decoded_sha256 and, on request, the ids and the offsets
    of the pieces: ``starts`` (code points) and ``upto`` (tokens up to each piece's end).

    Null and empty texts have no tokens; texts of any length are encoded whole; repeated rows come back
    as often; null ids stay; an empty table gives an empty result. Other columns are not read. The rank table
    goes to the executors once.
    """
    sent = df.sparkSession.sparkContext.broadcast(load_table(ranks_path))
    fields = [("doc", pa.int64()), ("n_tokens", pa.int64()), ("ids_sha256", pa.string()), ("decoded_sha256", pa.string())]
    fields += [("ids", pa.list_(pa.int32()))] * with_ids + [("starts", pa.list_(pa.int32())), ("upto", pa.list_(pa.int32()))] * with_offsets
    return _map(df, sent, pa.schema(fields), id_col, text_col)


def _map(df: DataFrame, sent, schema: pa.Schema, id_col: str, text_col: str) -> DataFrame:
    wanted = schema.names

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        codec, names = Codec(sent.value), [str(i) for i in range(max(sent.value.values()) + 1)]
        for whole in batches:
            for part in range(0, whole.num_rows, 200):
                batch = whole.slice(part, 200)
                rows: dict[str, list] = {c: [] for c in wanted[1:]}
                for e in codec.encode_batch(batch.column(1).to_pylist()):
                    rows["n_tokens"].append(len(e.ids))
                    rows["ids_sha256"].append(hashlib.sha256(" ".join(map(names.__getitem__, e.ids)).encode()).hexdigest())
                    rows["decoded_sha256"].append(hashlib.sha256(codec.decode(e.ids)).hexdigest())
                    for c, v in (("ids", e.ids), ("starts", e.starts), ("upto", e.upto)):
                        if c in rows:
                            rows[c].append(np.array(v, np.int32))
                yield pa.RecordBatch.from_arrays([batch.column(0), *[pa.array(v, schema.field(c).type) for c, v in rows.items()]], schema=schema)

    kinds = {"doc": "bigint", "n_tokens": "bigint", "ids": "array<int>", "starts": "array<int>", "upto": "array<int>"}
    out = ", ".join(f"{c} {kinds.get(c, 'string')}" for c in wanted)
    return df.select(column(id_col).cast("bigint").alias("doc"), F.coalesce(column(text_col), F.lit("")).alias("t")).mapInArrow(run, out).withColumnRenamed("doc", id_col)


def decode(df: DataFrame, ranks_path: str, id_col: str = "doc_id", ids_col: str = "ids") -> DataFrame:
    """(id, text) of rows of ids; a null array gives the empty text, a row without a number keeps none, repeated
    rows come back as often, an empty table gives an empty result. Bytes that are no UTF-8 on their own
    become replacement characters. Raises for an id that the table lacks."""
    sent = df.sparkSession.sparkContext.broadcast(load_table(ranks_path))

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        codec: Codec | None = None
        for b in batches:
            codec = codec or Codec(sent.value)
            texts = [codec.decode(x or []).decode("utf-8", "replace") for x in b.column(1).to_pylist()]
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(texts, pa.string())], names=["doc", "text"])

    return df.select(column(id_col).cast("bigint").alias("doc"), column(ids_col).alias("ids")).mapInArrow(run, "doc bigint, text string").withColumnRenamed("doc", id_col)


