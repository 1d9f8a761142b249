"""SimHash near-duplicates by pigeonhole blocks.

Fingerprints that differ in at most k of 64 bits, cut into m blocks, agree in at least m - k of them.
Every choice of m - k blocks makes a key; fingerprints meet under each key, and the Hamming distance
is verified within the key's group. Exact copies fall together before that (one row per distinct
fingerprint), and a group passes on a spanning forest of its links only, never all its pairs, so
that a dense group of g fingerprints yields g - 1 rows.
"""

from __future__ import annotations

from collections.abc import Iterable, Iterator
from itertools import combinations

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import Written, column, fold, packed, row_hash, unpacked
from .components import components

WORDS, SEED = 4, 42
#: Distinct fingerprints that one group may hold in a task.
MOST = 1 << 15


def fingerprint(text: str) -> int:
    """Majority vote, bit by bit, of the shingle hashes of an already folded text."""
    shingles = _shingles(text)
    if not shingles:
        return 0
    counts, n = np.zeros(64, np.int64), len(shingles)
    for at in range(0, n, 1 << 14):
        part = shingles[at : at + (1 << 14)]
        h = np.fromiter((xxhash.xxh64_intdigest(s, SEED) for s in part), np.uint64, len(part))
        counts += np.unpackbits(h.view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(0, dtype=np.int64)
    return int(np.packbits(2 * counts > n, bitorder="little").view(np.uint64)[0])


def _shingles(text: str) -> list[bytes]:
    w = text.encode("utf-8", "surrogatepass").split()
    if not w:
        return []
    if len(w) <= WORDS:
        return [b" ".join(w)]
    buf = b" ".join(w)
    ends = np.cumsum([len(x) + 1 for x in w])
    starts = ends - [len(x) + 1 for x in w]
    return [buf[a:b] for a, b in zip(starts[: 1 - WORDS].tolist(), (ends[WORDS - 1 :] - 1).tolist(), strict=True)]


def fingerprints(df: DataFrame, id_col: str = "doc_id", text_col: str = "text", hashed: bool = False) -> DataFrame:
    """(id, fp): the signed 64-bit pattern of each document's fingerprint. Null, empty and blank texts
    have fingerprint zero; repeated rows come back as often. hashed: also a and b, a hash of the text."""

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            fps = np.fromiter((fingerprint(t) for t in b.column(1).to_pylist()), np.uint64, b.num_rows)
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(fps.view(np.int64)), *b.columns[2:]], names=["id", "fp", "a", "b"][: b.num_columns])

    text = column(text_col)
    rows = df.select(column(id_col).cast("bigint").alias("id"), fold(text).alias("t"), *(_text_hash(text) if hashed else []))
    return rows.mapInArrow(run, "id bigint, fp bigint" + ", a bigint, b bigint" * hashed)


def _text_hash(text: Column) -> list[Column]:
    """128 bits of a text as it stands, null as the empty one."""
    text = F.coalesce(text, F.lit(""))
    return [F.xxhash64(text).alias("a"), F.xxhash64(text, F.lit(1)).alias("b")]


def layout(n: int, k: int, width: int = 64) -> list[tuple[int, int]]:
    """(lowest bit, width) of the blocks. More fingerprints need longer keys: with n of them a key of
    about log2(n) bits keeps the chance meetings per row constant. Every layout is exact."""
    agree = 1
    while (agree + 1) * width // (agree + 1 + k) <= 30 and agree * width // (agree + k) < np.log2(max(n, 2)):
        agree += 1
    m = agree + k
    edges = [width * i // m for i in range(m + 1)]
    return [(a, b - a) for a, b in zip(edges, edges[1:])]


def _packed(blocks: Iterable[tuple[int, int]]) -> Column:
    out = F.lit(0).cast("bigint")
    for lo, width in blocks:
        out = F.shiftleft(out, width).bitwiseOR(F.shiftrightunsigned("rest", lo).bitwiseAND(F.lit((1 << width) - 1)))
    return out


def _split(rows: DataFrame, blocks: list[tuple[int, int]], k: int) -> DataFrame:
    """rows (g, fp, rest), ``rest`` the bits in which members of group g may still differ, under every
    choice of blocks that agree. A group's name is a hash: groups that share one are only compared more."""
    out = []
    for t, chosen in enumerate(combinations(blocks, len(blocks) - k)):
        out.append(F.struct(F.xxhash64("g", F.lit(t), _packed(chosen)).alias("g"), _packed([b for b in blocks if b not in chosen]).alias("rest")))
    return rows.select("fp", F.explode(F.array(*out)).alias("x")).select("x.g", "fp", "x.rest")


def forest(fps: np.ndarray, k: int) -> list[tuple[int, int]]:
    """Spanning forest of the links among distinct fingerprints, as index pairs. A grown component
    claims all it reaches, row by row: a fingerprint once claimed is compared as a source only once,
    and the unclaimed shrink, so dense groups take few rows."""
    free, out = np.arange(len(fps)), []
    while len(free) > 1:
        queue, free = [int(free[0])], free[1:]
        while queue and len(free):
            i = queue.pop()
            near = np.bitwise_count(fps[free] ^ fps[i]) <= k
            if near.any():
                out += [(i, int(j)) for j in free[near]]
                queue += free[near].tolist()
                free = free[~near]
    return out


def _meet(rows: DataFrame, k: int, most: int | None) -> DataFrame:
    """(u, v, rest) of rows (g, fp, rest): links of each group, with a null rest, as a spanning forest. A
    group of more than ``most`` members is not held: its rows come back as they are, (g, fp, rest)."""

    def batch(u: np.ndarray, v: np.ndarray, rest: np.ndarray | None) -> pa.RecordBatch:
        last = pa.nulls(len(u), pa.int64()) if rest is None else pa.array(rest)
        return pa.RecordBatch.from_arrays([pa.array(u), pa.array(v), last], names=["u", "v", "rest"])

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        def close(rows: np.ndarray) -> Iterator[pa.RecordBatch]:
            """rows: whole groups, sorted by g."""
            new = np.flatnonzero(np.append(True, rows[1:, 0] != rows[:-1, 0]))
            size = np.diff(np.append(new, len(rows)))
            at = new[size == 2]
            pair = rows[at, 1], rows[at + 1, 1]
            near = np.bitwise_count((pair[0] ^ pair[1]).view(np.uint64)) <= k
            u, v = [pair[0][near]], [pair[1][near]]
            for a, s in zip(new[size > 2].tolist(), size[size > 2].tolist(), strict=True):
                fps = rows[a : a + s, 1]
                if most is not None and s > most:
                    yield batch(*np.ascontiguousarray(rows[a : a + s].T))
                elif e := forest(fps.view(np.uint64), k):
                    i, j = np.array(e).T
                    u.append(fps[i])
                    v.append(fps[j])
            yield batch(np.concatenate(u), np.concatenate(v), None)

        held, passing = np.zeros((0, 3), np.int64), None  # passing: a group that goes through unheld
        for b in batches:
            rows = np.stack([c.to_numpy(zero_copy_only=False).astype(np.int64) for c in b.columns], 1)
            if passing is not None:
                n = int((rows[:, 0] == passing).sum())
                if n:
                    yield batch(*np.ascontiguousarray(rows[:n].T))
                rows = rows[n:]
            rows = np.concatenate([held, rows])
            if not len(rows):
                continue
            passing = None
            cut = len(rows) - int((rows[:, 0] == rows[-1, 0]).sum())  # the last group may go on in the next batch
            if cut:
                yield from close(rows[:cut])
            held = np.ascontiguousarray(rows[cut:])
            if most is not None and len(held) > most:
                yield batch(*np.ascontiguousarray(held.T))
                held, passing = held[:0], held[0, 0]
        if len(held):
            yield from close(held)

    return rows.repartition("g").sortWithinPartitions("g").select("g", "fp", "rest").mapInArrow(run, "u bigint, v bigint, rest bigint")


def links(distinct: DataFrame, written: Written, k: int = 4, n: int | None = None, most: int = MOST) -> DataFrame:
    """(u, v): fingerprint pairs within k bits whose closure is that of all such pairs.

    A group of more than ``most`` fingerprints is cut by blocks of the bits that its key left open, which
    thins it out unless its members are alike. A group that is still as large is dealt into parts, and
    each two parts meet in a group of their own, so that no task holds more than about ``most``."""
    n = distinct.count() if n is None else n
    rows, width, out = distinct.select(F.lit(0).cast("bigint").alias("g"), "fp", F.col("fp").alias("rest")), 64, None
    for _ in range(2):
        blocks = layout(n, k, width)
        found = written.save(_meet(_split(rows, blocks, k), k, most))
        width -= sum(sorted(w for _, w in blocks)[: len(blocks) - k])
        now = found.where("rest is null").select("u", "v")
        out = now if out is None else out.union(now)
        rows = found.where("rest is not null").select(F.col("u").alias("g"), F.col("v").alias("fp"), "rest")
        n = rows.groupBy("g").count().agg(F.max("count")).first()[0]
        if n is None:
            return out
    sizes = rows.groupBy(F.col("g").alias("of")).agg(F.ceil(2 * F.count(F.lit(1)) / F.lit(most)).cast("bigint").alias("parts"))
    dealt = rows.join(sizes, F.col("g") == F.col("of")).withColumn("a", F.pmod(F.xxhash64("fp"), F.col("parts")))
    dealt = dealt.withColumn("b", F.explode(F.sequence(F.lit(0).cast("bigint"), F.col("parts") - 1))).where("a <> b")
    met = dealt.select(F.xxhash64("g", F.least("a", "b"), F.greatest("a", "b")).alias("g"), "fp", "rest")
    return out.union(_meet(met, k, None).select("u", "v"))


def groups(fps: DataFrame, written: Written, k: int) -> DataFrame:
    """(root, fp, least, component) of each distinct fingerprint: a name of its component that no other
    has, its smallest id and that of its component, null if all are."""
    distinct = written.save(fps.groupBy("fp").agg(F.min("id").alias("least")))
    comp = components(links(distinct.select("fp"), written, k), written)
    rooted = distinct.join(comp, distinct.fp == comp.id, "left").select("fp", "least", F.coalesce("root", "fp").alias("root"))
    low = rooted.groupBy("root").agg(F.min("least").alias("component"))
    return rooted.join(low, "root")


def near_duplicates(df: DataFrame, written: Written, id_col: str = "doc_id", text_col: str = "text", k: int = 4) -> DataFrame:
    """One row per document: its id, fingerprint (16 hexadecimal digits) and component_id, the
    smallest id reachable over links of at most k differing bits, itself included.

    Null, empty and blank texts share fingerprint zero and link like any other. Repeated rows come back
    as often. An empty table gives an empty result. Other columns are not read. A group under one key
    holds distinct fingerprints only; a text that a third of all documents share counts once in it.
    """
    fps = written.save(fingerprints(df, id_col, text_col))
    named = written.save(groups(fps, written, k).select("fp", "component"))
    return fps.join(named, "fp").select(F.col("id").alias(id_col), F.lpad(F.lower(F.hex("fp")), 16, "0").alias("fingerprint"), F.col("component").alias("component_id"))


def keep_one(df: DataFrame, written: Written, id_col: str = "doc_id", text_col: str = "text", k: int = 4) -> DataFrame:
    """One row of each component with all its columns, whatever their names and types: that of the smallest
    id, null after all others. Rows are told apart by id and text, so one id may stay with several texts that
    are not near copies; of near copies that share the smallest id, the text with the least hash stays, and of rows
    that repeat id and text, the one with the least hash of the whole row. Null texts count as empty; an
    empty table gives an empty result."""
    key = ["id", "no", "a", "b"]
    fps = written.save(fingerprints(df, id_col, text_col, hashed=True))
    named = written.save(groups(fps, written, k).select("fp", "root", "component"))
    best = fps.join(named, "fp").where(F.col("id").eqNullSafe(F.col("component"))).groupBy("root").agg(F.min(F.struct("id", "a", "b")).alias("x"))
    chosen = best.select(F.coalesce("x.id", F.lit(0)).alias("id"), F.col("x.id").isNull().alias("no"), "x.a", "x.b")
    ident, (a, b) = column(id_col).cast("bigint"), _text_hash(column(text_col))
    rows = packed(df, id=F.coalesce(ident, F.lit(0)), no=ident.isNull(), a=a, b=b, h=row_hash(df))
    return unpacked(rows.join(chosen, key, "left_semi").groupBy(*key).agg(F.min_by("row", "h").alias("row")), df)
