"""Exact deduplication with owners kept in Patricia tries.

Each task first combines the copies within its own rows (a bounded map-side combiner), so that a text
which a third of all rows share crosses the exchange once per task. Distinct texts are dealt out by
length and content hash; each partition inserts the full byte strings into a compressed radix trie
whose terminal nodes hold the owner and the number of copies. A trie over its memory bound spills
whole subtrees, the largest first, and finishes them one by one, all in the host's spill folder of Spark. The members then learn their owner
by a join key that is unique to a task's copies, so no key is hot.
"""

from __future__ import annotations

import hashlib
import os
import pickle
import tempfile
from collections.abc import Callable, Iterable, Iterator
from itertools import islice

import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import column, fold, packed, row_hash, unpacked

#: Bytes of text that a combiner holds before it passes its groups on, and a trie before it spills.
COMBINER_BYTES, TRIE_BYTES = 32 << 20, 64 << 20
#: What a node and a member are taken to weigh, members that a node holds before they go to a file of their
#: own, and files that one spill opens.
NODE_BYTES, MEMBER_BYTES, MOST_MEMBERS, SPILL_FILES = 300, 150, 4096, 8


def scratch():
    """A nameless file where Spark keeps its own spills on this host; it vanishes with the task, which
    starts anew if its executor is lost."""
    at = os.environ.get("SPARK_LOCAL_DIRS", "").split(",")[0]
    return tempfile.TemporaryFile(dir=at if at and os.path.isdir(at) else None)


def records(f) -> Iterator[tuple]:
    """What was pickled to a file, from its start."""
    f.seek(0)
    while True:
        try:
            yield pickle.load(f)
        except EOFError:
            return


class Node:
    __slots__ = ("label", "kids", "best", "count", "members", "more")

    def __init__(self, label: bytes):
        self.label, self.kids, self.best, self.count, self.members, self.more = label, {}, None, 0, (), None

    def chunks(self) -> Iterator[list]:
        """The members, those that went to a file first."""
        if self.more is not None:
            yield from records(self.more)
        yield list(self.members)


class PatriciaOwners:
    """Compressed radix trie over byte strings. A terminal node keeps the best identifier put there
    (the smallest, or the largest with ``largest``), the number of copies and the members put with them.

    Over ``max_bytes`` it spills the heaviest subtrees below the place where it branches, wherever that is;
    their kids' places then hold the file, to which later strings of the subtree go unread. Each file is
    finished by a trie of its own, which may spill again."""

    def __init__(self, largest: bool = False, max_bytes: int = TRIE_BYTES):
        self.better: Callable = (lambda a, b: a > b) if largest else (lambda a, b: a < b)
        self.largest, self.max_bytes, self.bytes = largest, max_bytes, 0
        self.root, self.spills = Node(b""), 0

    def insert(self, key: bytes, ident, count: int = 1, members: tuple = ()) -> None:
        node, at = self.root, 0
        while at < len(key):
            kid = node.kids.get(key[at])
            if kid is None:
                kid = node.kids[key[at]] = Node(key[at:])
                self.bytes += len(kid.label) + NODE_BYTES
                at = len(key)
            elif type(kid) is not Node:
                pickle.dump((key[at:], ident, count, members), kid)
                return
            elif key.startswith(kid.label, at):
                at += len(kid.label)
            else:
                label, n = kid.label, shared(kid.label, key, at)
                middle = node.kids[key[at]] = Node(label[:n])
                middle.kids[label[n]], kid.label = kid, label[n:]
                self.bytes += NODE_BYTES
                kid, at = middle, at + n
            node = kid
        node.count += count
        if members:
            if not node.members:
                node.members = []
            node.members += members
            self.bytes += MEMBER_BYTES * len(members)
            if len(node.members) > MOST_MEMBERS:
                node.more = node.more or scratch()
                pickle.dump(node.members, node.more)
                self.bytes, node.members = self.bytes - MEMBER_BYTES * len(node.members), ()
        if node.best is None or self.better(ident, node.best):
            node.best = ident
        if self.bytes > self.max_bytes:
            self._spill()

    def _walk(self, node: Node, prefix: bytes) -> Iterator[tuple[bytes, Node]]:
        stack = [(node, prefix)]
        while stack:
            x, p = stack.pop()
            p += x.label
            if x.count:
                yield p, x
            stack += [(k, p) for k in x.kids.values() if type(k) is Node]

    def _files(self, node: Node, prefix: bytes) -> list[tuple]:
        """(file, path to the node whose kids it holds) of all that was spilled below ``node``."""
        out, stack = {}, [(node, prefix)]
        while stack:
            x, p = stack.pop()
            p += x.label
            for k in x.kids.values():
                if type(k) is Node:
                    stack.append((k, p))
                else:
                    out[id(k)] = k, p
        return list(out.values())

    def _weights(self) -> dict[int, int]:
        """Bytes held by the subtree of each node."""
        order, stack = [], [self.root]
        while stack:
            x = stack.pop()
            order.append(x)
            stack += [k for k in x.kids.values() if type(k) is Node]
        out: dict[int, int] = {}
        for x in reversed(order):
            own = NODE_BYTES + len(x.label) + MEMBER_BYTES * len(x.members)
            out[id(x)] = own + sum(out[id(k)] for k in x.kids.values() if type(k) is Node)
        return out

    def _spill(self) -> None:
        """Moves the heaviest subtrees, until half is free, to files. It starts below what all heavy strings
        have in common: a node whose one kid holds most of the weight has no choice to offer."""
        weight, node = self._weights(), self.root
        held = lambda x: {b: k for b, k in x.kids.items() if type(k) is Node}
        while True:
            first = max((k for k in held(node).values()), key=lambda k: weight[id(k)], default=None)
            if first is None or 2 * weight[id(first)] <= self.bytes or not held(first):
                break
            node = first
        files, free = [], 0
        if sum(1 for _ in islice(self._walk(self.root, b""), 2)) < 2:  # one string with its members: nothing to part
            self.max_bytes = 2 * self.bytes
            return
        for b, kid in sorted(held(node).items(), key=lambda e: -weight[id(e[1])]):
            if free >= self.bytes // 2:
                break
            if len(files) < SPILL_FILES:
                files.append(scratch())
                self.spills += 1
            out = node.kids[b] = files[len(files) - 1]
            for key, x in self._walk(kid, b""):
                for i, chunk in enumerate(x.chunks()):
                    pickle.dump((key, x.best, 0 if i else x.count, chunk), out)
            for f, prefix in self._files(kid, b""):  # what was spilled below it before
                for key, *rest in records(f):
                    pickle.dump((prefix + key, *rest), out)
                f.close()
            free += weight[id(kid)]
        self.bytes = max(0, self.bytes - free)
        if not free:  # all that is left hangs on the way to what was spilled before
            self.max_bytes = 2 * self.bytes

    def groups(self) -> Iterator[tuple[bytes, object, int, Iterator[list]]]:
        """(text, best identifier, copies, members in chunks) of every text, the spilled subtrees last, one at a
        time."""
        yield from ((p, x.best, x.count, x.chunks()) for p, x in self._walk(self.root, b""))
        files, self.root = self._files(self.root, b""), Node(b"")
        for f, prefix in files:
            below = PatriciaOwners(self.largest, self.max_bytes)
            for record in records(f):
                below.insert(*record)
            f.close()
            self.spills += below.spills
            for key, best, count, members in below.groups():
                yield prefix + key, best, count, members

    def owners(self) -> Iterator[tuple[bytes, object, int]]:
        """(text, best identifier, copies) of every text."""
        yield from ((text, best, count) for text, best, count, _ in self.groups())


def shared(label: bytes, key: bytes, at: int) -> int:
    """Length of the common start of ``label`` and ``key[at:]``, by halving."""
    lo, hi = 0, min(len(label), len(key) - at)
    while lo < hi:
        mid = (lo + hi + 1) // 2
        if label[:mid] == key[at : at + mid]:
            lo = mid
        else:
            hi = mid - 1
    return lo


COMBINED = pa.schema([("doc", pa.int64()), ("rep", pa.int64()), ("len", pa.int64()), ("h", pa.int64()), ("text", pa.binary()), ("n", pa.int64())])
OWNED = pa.schema([("doc", pa.int64()), ("rep", pa.int64()), ("keep", pa.int64()), ("size", pa.int64()), ("sha", pa.string()), ("owns", pa.bool_())])


def ordered(doc: int | None, largest: bool) -> int | float:
    """A null identifier is worse than any other."""
    return doc if doc is not None else float("-inf") if largest else float("inf")


def _combine(largest: bool) -> Callable[[Iterable[pa.RecordBatch]], Iterator[pa.RecordBatch]]:
    """A row with the text for each distinct text of the task, its document the task's best; a row
    without text for each other copy. ``rep`` is unique to the task's group."""

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        task, serial, held = TaskContext.get().partitionId() << 40, 0, 0
        groups: dict[bytes, list] = {}

        def flush() -> Iterator[pa.RecordBatch]:
            nonlocal groups, held
            rows: list[tuple] = []
            for text, (rep, best, h, others) in groups.items():
                rows.append((best, rep, len(text), h, text, 1 + len(others)))
                rows += [(x, rep, None, None, None, None) for x in others]
                if len(rows) >= 2000:
                    yield batch_of(rows, COMBINED)
                    rows = []
            if rows:
                yield batch_of(rows, COMBINED)
            groups, held = {}, 0

        for batch in batches:
            for doc, text, h in zip(*(c.to_pylist() for c in batch.columns), strict=True):
                if (g := groups.get(text)) is None:
                    groups[text] = [task + serial, doc, h, []]
                    serial, held = serial + 1, held + len(text) + 400
                elif doc != g[1] and (ordered(doc, largest) > ordered(g[1], largest)) == largest:
                    g[3].append(g[1])
                    g[1] = doc
                    held += 40
                else:
                    g[3].append(doc)
                    held += 40
            if held > COMBINER_BYTES:
                yield from flush()
        yield from flush()

    return run


def batch_of(rows: list[tuple], schema: pa.Schema) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array(c, t.type) for c, t in zip(zip(*rows, strict=True), schema, strict=True)], schema=schema)


def _own(largest: bool) -> Callable[[Iterable[pa.RecordBatch]], Iterator[pa.RecordBatch]]:
    """Members pass through. Each group that held a text gets its owner: identifiers in the trie are
    (document, group), so exactly one group owns a text even where documents repeat. The groups of a text
    wait at its terminal node, so that nothing is kept beside the trie, whose bytes are bounded."""

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        trie, rows = PatriciaOwners(largest), []
        for batch in batches:
            for doc, rep, _, _, text, n in zip(*(c.to_pylist() for c in batch.columns), strict=True):
                if text is None:
                    rows.append((doc, rep, None, None, None, False))
                else:
                    trie.insert(text, (ordered(doc, largest), rep), n, ((doc, rep),))
            if len(rows) >= 2000:
                yield batch_of(rows, OWNED)
                rows = []
        for text, (keep, owner), count, chunks in trie.groups():
            sha, keep = hashlib.sha256(text).hexdigest(), None if isinstance(keep, float) else keep
            for members in chunks:
                rows += [(doc, rep, keep, count, sha, owner == rep) for doc, rep in members]
                if len(rows) >= 2000:
                    yield batch_of(rows, OWNED)
                    rows = []
        if rows:
            yield batch_of(rows, OWNED)

    return run


def owners(df: DataFrame, id_col: str = "doc_id", text_col: str = "text", largest: bool = False) -> DataFrame:
    """One row per input row: its id, keep_id, group_size, kept and text_sha256 of the folded text.

    Texts are equal when identical after folding A-Z. Null counts as empty, and all empty texts are
    one group. Of equal texts that repeat the winning id too, one row is kept. Ids must be whole
    numbers; a null id wins only among null ids. An empty table gives an empty result. Other columns are not read.
    """
    text = fold(column(text_col))
    keyed = df.select(column(id_col).cast("bigint").alias("doc"), text.cast("binary").alias("text"), F.xxhash64(text).alias("h"))
    combined = keyed.mapInArrow(_combine(largest), "doc bigint, rep bigint, len bigint, h bigint, text binary, n bigint")
    # Rows without a text need no partner here: they are spread by their document.
    dealt = combined.repartition(F.coalesce(F.xxhash64("len", "h"), F.lit(0)), F.when(F.col("text").isNull(), F.col("doc")))
    owned = dealt.mapInArrow(_own(largest), "doc bigint, rep bigint, keep bigint, size bigint, sha string, owns boolean")
    group = Window.partitionBy("rep")
    return owned.select(
        F.col("doc").alias(id_col),
        F.max("keep").over(group).alias("keep_id"),
        F.max("size").over(group).alias("group_size"),
        F.col("owns").alias("kept"),
        F.max("sha").over(group).alias("text_sha256"),
    )


def deduplicate(df: DataFrame, id_col: str = "doc_id", text_col: str = "text", largest: bool = False) -> DataFrame:
    """The rows that stay, with all their columns, whatever their names and types. Rows that repeat both id
    and text stay once; of those that differ in letter case or other columns, the one with the least hash of the
    whole row. A row whose id is null stays if no other has its text. Null texts count as empty; an empty
    table gives an empty result."""
    key = ["id", "no", "sha"]
    kept = owners(df, id_col, text_col, largest).where("kept").select(F.coalesce(column(id_col), F.lit(0)).alias("id"), column(id_col).isNull().alias("no"), F.col("text_sha256").alias("sha"))
    ident = column(id_col).cast("bigint")
    rows = packed(df, id=F.coalesce(ident, F.lit(0)), no=ident.isNull(), sha=F.sha2(fold(column(text_col)).cast("binary"), 256), h=row_hash(df))
    first = rows.join(kept, key, "left_semi").groupBy(*key).agg(F.min_by("row", "h").alias("row"))
    return unpacked(first, df)


SQL = """
with d as (select doc_id, translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') as t from documents),
w as (select doc_id, t, max(doc_id) over (partition by t) as keep_id, count(*) over (partition by t) as n from d)
select doc_id, keep_id, cast(n as bigint) as group_size, doc_id = keep_id as kept, sha256(t) as text_sha256 from w
"""
