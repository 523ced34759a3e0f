"""N-gram Jaccard self-join through a MinHash LSH forest, verified exactly.

Documents with equal sets of word shingles form a class, told apart by 128-bit set hashes. Each class has a key in
every one of ``TREES`` trees: ``LEVELS`` MinHash values of one byte, the first one highest, so that sorted keys are a
prefix trie. The search starts at whole keys and shortens them, level by level, to the depth at which a link would
share a prefix in some tree with a chance of ``TARGET_RECALL``. That depth is a class's own: it follows from
the weakest link that a set of its size can have (a set of 5 shingles has none below 4/5, one of 7 none below 6/7),
so short texts keep long prefixes. Two classes meet in a tree if they share a prefix of the longer of their depths.

Classes that meet are compared by ``SKETCH`` of their MinHash values, in the subtree where they meet; only those
that agree in ``AGREE`` of them are joined into candidate groups (a link falls below that with a chance under
10^-11), so unlike texts that meet by chance make no large groups. A subtree of more than ``SUBTREE`` classes is dealt
out by pairs of blocks. Inside a group every pair's exact similarity is taken from the shingle sets in
blocks of matrix products: a task holds at most two blocks of ``BLOCK`` classes, larger groups are dealt out by
pairs of blocks. No pair leaves a task: only each class's number of links and the edges of a spanning forest do.

Defined cases: words are runs outside ``[\\x00-\\x2F\\x3A-\\x60\\x7B-\\x7F]`` with A-Z lower-cased; a text of
fewer than ``k`` words, but not none, has one shingle of all its words; texts without words (null, empty)
form one class and are linked to nothing else; repeated rows count as copies; an empty table gives no
rows; null doc_ids are kept and never represent a group that has another id; other columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from sparkcurate.functions.arrow import group_arrow, map_arrow
from sparkcurate.functions.lineage import cut
from sparkcurate.llm.textscan import U, Words, distinct_by_row, mix, shingles, slices, text_bytes
from sparkcurate.operators.components import connected_components

SHINGLE = 5
# similarity of at least 4 / 5
THRESHOLD = (4, 5)
TREES = 32
LEVELS = 8
TARGET_RECALL = 0.9999
# values of a class's sketch (the keys of its first trees), and how many must agree
SKETCH = 128
AGREE = 70
# classes of a subtree that are compared in one task
SUBTREE = 4096
BLOCK = 2048
# classes a verifying task gets when groups are small
GROUP_CLASSES = 1024
_COLUMNS = 8192
# subtrees of so many classes at most are compared all together
_SMALL = 8
_WALK_ROWS = 20_000


def forest_depth(similarity: float, trees: int = TREES, recall: float = TARGET_RECALL, levels: int = LEVELS) -> int:
    """The longest prefix at which pairs of this similarity still meet with the target recall."""
    for depth in range(levels, 1, -1):
        if 1 - (1 - similarity**depth) ** trees >= recall:
            return depth
    return 1


@lru_cache(maxsize=4096)
def weakest_link(n: int, threshold: tuple[int, int] = THRESHOLD) -> float:
    """The least similarity, at the threshold or above, of a set of n shingles and an unequal one (1 if there is none)."""
    p, q = threshold
    found = [both / (n + m - both) for m in range(max(1, n * p // q), n * q // p + 2) for both in range(1, min(n, m) + 1) if both < max(n, m) and both * q >= p * (n + m - both)]
    return min(found, default=1.0)


@lru_cache(maxsize=4096)
def class_depth(n: int, threshold: tuple[int, int] = THRESHOLD, trees: int = TREES, recall: float = TARGET_RECALL) -> int:
    """The depth to which the keys of a set of n shingles are shortened; beyond 64 shingles the threshold's."""
    return forest_depth(weakest_link(n, threshold) if n <= 64 else threshold[0] / threshold[1], trees, recall)


def _shingle_sets(batch: pa.RecordBatch, k: int) -> tuple[np.ndarray, np.ndarray]:
    words = Words(*text_bytes(batch.column("text")))
    return distinct_by_row(*shingles(words, k))


def _class_hashes(hashes: np.ndarray, rows: np.ndarray, n: int) -> list[bytes]:
    """16 bytes a row, the same for equal sets."""
    count = np.bincount(rows, minlength=n)
    starts = np.concatenate([[0], np.cumsum(count)])[:-1]
    out = np.zeros((n, 2), np.uint64)
    if len(hashes):
        some = count > 0
        mixed = mix(hashes)
        out[some, 0] = np.add.reduceat(mixed, starts[some])
        out[some, 1] = np.add.reduceat(mix(mixed + U(0x2545F4914F6CDD1D)), starts[some])
    return mix(out + count.astype(np.uint64)[:, None]).astype(">u8").view("V16").reshape(-1).tolist()


def _sign(k: int, threshold: tuple[int, int], trees: int, recall: float):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        seeds = mix(np.arange(1, 2 * trees * LEVELS + 1, dtype=np.uint64))
        times, plus = seeds[::2] | U(1), seeds[1::2]
        for batch in slices(batches):
            n = batch.num_rows
            hashes, rows = _shingle_sets(batch, k)
            count = np.bincount(rows, minlength=n)
            some = np.flatnonzero(count)
            starts = np.concatenate([[0], np.cumsum(count)])[:-1][some]
            keys = np.zeros((len(some), trees), np.uint64)
            for j in range(trees * LEVELS if len(some) else 0):
                low = mix(np.minimum.reduceat((hashes * times[j] + plus[j]) >> U(16), starts)) & U(255)
                keys[:, j // LEVELS] = (keys[:, j // LEVELS] << U(8)) | low
            offsets = np.zeros(n + 1, np.int32)
            offsets[1:] = np.cumsum((count > 0) * trees)
            depth = [class_depth(c, threshold, trees, recall) if c else 0 for c in np.minimum(count, 65).tolist()]
            listed = pa.ListArray.from_arrays(pa.array(offsets), pa.array(keys.reshape(-1).view(np.int64)))
            yield pa.RecordBatch.from_arrays(
                [batch.column("doc_id"), batch.column("digest"), pa.array(_class_hashes(hashes, rows, n), pa.binary()), pa.array(depth, pa.int32()), listed],
                ["doc_id", "digest", "node", "depth", "keys"],
            )

    return run


def _meetings(key: np.ndarray, depth: np.ndarray, sketch: np.ndarray, side: np.ndarray) -> list[tuple[int, int]]:
    """Spanning edges of the classes of one subtree that agree; side tells two blocks apart (only rows of unlike sides meet, if there are two)."""
    n = len(key)
    top = np.arange(n)
    edges: list[tuple[int, int]] = []
    both = side.min() != side.max()
    for level in range(LEVELS, 0, -1):
        open_ = np.flatnonzero(depth <= level)
        if not len(open_):
            break
        prefix = key[open_] >> U(8 * (LEVELS - level))
        # keys are sorted, so a node of the trie is a run of equal prefixes
        cuts = np.flatnonzero(np.diff(prefix)) + 1
        for node in np.split(open_, cuts):
            if len(node) < 2 or (top[node] == top[node[0]]).all():
                continue
            for x in range(len(node) - 1):
                i, rest = node[x], node[x + 1 :]
                rest = rest[top[rest] != top[i]]
                if both:
                    rest = rest[side[rest] != side[i]]
                if not len(rest):
                    continue
                for j in rest[(sketch[rest] == sketch[i]).sum(axis=1) >= AGREE].tolist():
                    if top[j] != top[i]:
                        edges.append((int(i), j))
                        top[top == top[j]] = top[i]
    return edges


def _walk(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Rows arrive sorted by subtree (prefix, i, j) and key; gives the edges (a, b) of classes that agree."""

    def met(table: pa.Table, cuts: np.ndarray) -> pa.RecordBatch | None:
        key = np.asarray(table.column("key")).view(np.uint64)
        depth, side = np.asarray(table.column("depth")), np.asarray(table.column("block"))
        sketch = np.frombuffer(b"".join(table.column("sketch").to_pylist()), np.uint8).reshape(len(key), -1)
        size = np.diff(cuts)
        a, b = [], []
        small = np.flatnonzero((size > 1) & (size <= _SMALL))
        for x in range(_SMALL - 1):
            for y in range(x + 1, _SMALL):
                some = cuts[:-1][small[size[small] > y]]
                i, j = some + x, some + y
                need = np.maximum(depth[i], depth[j])
                near = ((key[i] ^ key[j]) >> ((LEVELS - need) * 8).astype(np.uint64)) == 0
                i, j = i[near], j[near]
                if len(i):
                    good = (sketch[i] == sketch[j]).sum(axis=1) >= AGREE
                    a += i[good].tolist()
                    b += j[good].tolist()
        for s in np.flatnonzero(size > _SMALL).tolist():
            lo, hi = cuts[s], cuts[s + 1]
            # unsigned order of the keys
            order = lo + np.argsort(key[lo:hi], kind="stable")
            for i, j in _meetings(key[order], depth[order], sketch[order], side[order]):
                a.append(int(order[i]))
                b.append(int(order[j]))
        if not a:
            return None
        node = table.column("node").combine_chunks()
        return pa.RecordBatch.from_arrays([node.take(pa.array(a)), node.take(pa.array(b))], ["a", "b"])

    held: list[pa.RecordBatch] = []
    rows = 0
    want = _WALK_ROWS
    for batch in batches:
        held.append(batch)
        rows += batch.num_rows
        if rows < want:
            continue
        table = pa.Table.from_batches(held).combine_chunks()
        cuts = _runs(table)
        if len(cuts) > 2:
            if (out := met(table.slice(0, cuts[-2]), cuts[:-1])) is not None:
                yield out
            held, rows, want = table.slice(cuts[-2]).to_batches(), table.num_rows - int(cuts[-2]), _WALK_ROWS
        else:
            held, want = table.to_batches(), 2 * rows
    if rows:
        table = pa.Table.from_batches(held).combine_chunks()
        if (out := met(table, _runs(table))) is not None:
            yield out


def _runs(table: pa.Table) -> np.ndarray:
    """Starts of the runs of one subtree, and the number of rows."""
    columns = [np.asarray(table.column(c)) for c in ("prefix", "i", "j")]
    new = np.zeros(table.num_rows - 1, bool)
    for c in columns:
        new |= c[1:] != c[:-1]
    return np.concatenate([[0], np.flatnonzero(new) + 1, [table.num_rows]])


def _collect_sets(k: int):
    columns = ("node", "size", "group", "blocks", "block")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        seen: set[bytes] = set()
        for batch in slices(batches):
            n = batch.num_rows
            hashes, rows = _shingle_sets(batch, k)
            first = np.searchsorted(rows, np.arange(n + 1))
            own = _class_hashes(hashes, rows, n)
            # repeated rows of a class's first document are read once a task
            same = []
            for i, (is_, wanted) in enumerate(zip(own, batch.column("node").to_pylist(), strict=True)):
                if is_ == wanted and wanted not in seen:
                    seen.add(wanted)
                    same.append(i)
            sets = [hashes[first[i] : first[i + 1]].tobytes() for i in same]
            kept = batch.take(pa.array(same, pa.int64()))
            yield pa.RecordBatch.from_arrays([*(kept.column(c) for c in columns), pa.array(sets, pa.binary())], [*columns, "shingles"])

    return run


def _intersections(left: list[np.ndarray], right: list[np.ndarray] | None) -> np.ndarray:
    """Sizes of all intersections, by products of 0/1 matrices over the shingles that occur twice."""
    every = left if right is None else [*left, *right]
    owner = np.repeat(np.arange(len(every)), [len(s) for s in every])
    flat = np.concatenate(every)
    _, column, times = np.unique(flat, return_inverse=True, return_counts=True)
    shared = times > 1
    number = np.cumsum(shared) - 1
    owner, column = owner[shared[column]], number[column[shared[column]]]
    order = np.argsort(column, kind="stable")
    owner, column = owner[order], column[order]
    out = np.zeros((len(left), len(every) if right is None else len(right)), np.float64)
    for a in range(0, int(shared.sum()), _COLUMNS):
        lo, hi = np.searchsorted(column, [a, a + _COLUMNS])
        dense = np.zeros((len(every), min(_COLUMNS, int(shared.sum()) - a)), np.float32)
        dense[owner[lo:hi], column[lo:hi] - a] = 1
        out += dense[: len(left)] @ (dense if right is None else dense[len(left) :]).T
    return out


def _parts(linked: np.ndarray, square: bool) -> tuple[np.ndarray, np.ndarray]:
    """Number of the connected part of each row and column (of a square matrix they are the same things)."""
    n, m = linked.shape
    row, column = np.full(n, -1), np.full(m, -1)
    for i in range(n):
        if row[i] >= 0:
            continue
        row[i] = i
        new = np.array([i])
        while len(new):
            if square:
                new = np.flatnonzero(linked[new].any(axis=0) & (row < 0))
            else:
                reached = np.flatnonzero(linked[new].any(axis=0) & (column < 0))
                column[reached] = i
                new = np.flatnonzero(linked[:, reached].any(axis=1) & (row < 0)) if len(reached) else reached
            row[new] = i
    return row, row if square else column


def _verify(threshold: tuple[int, int]):
    p, q = threshold

    def links_of(left, right, sets):
        inter = _intersections([sets[i] for i in left], None if right is None else [sets[i] for i in right])
        a = np.array([len(sets[i]) for i in left])
        b = a if right is None else np.array([len(sets[i]) for i in right])
        linked = (inter * (p + q) >= p * (a[:, None] + b[None, :])) & (inter > 0)
        if right is None:
            np.fill_diagonal(linked, False)
        return linked

    def run(key: tuple[pa.Scalar, ...], table: pa.Table) -> pa.Table:
        node = table.column("node").to_pylist()
        group, block = (np.asarray(table.column(c)) for c in ("group", "block"))
        first = sorted({(n, g, b): i for i, (n, g, b) in reversed(list(enumerate(zip(node, group, block.tolist(), strict=True))))}.values())
        table = table.take(pa.array(first))
        node = table.column("node").to_pylist()
        size, block = (np.asarray(table.column(c)) for c in ("size", "block"))
        _, group = np.unique(np.array(table.column("group").to_pylist(), object), return_inverse=True)
        sets = [np.frombuffer(s, np.uint64) for s in table.column("shingles").to_pylist()]
        links, top = np.zeros(len(node), np.int64), np.arange(len(node))
        cross = int(key[1].as_py()) != int(key[2].as_py())
        order = np.argsort(group, kind="stable")
        for members in np.split(order, np.flatnonzero(np.diff(group[order])) + 1):
            mine = np.unique(block[members])
            if cross and len(mine) < 2:
                continue
            left = members[block[members] == mine[0]]
            right = members[block[members] == mine[1]] if cross else None
            linked = links_of(left.tolist(), None if right is None else right.tolist(), sets)
            others = left if right is None else right
            links[left] += linked @ size[others]
            row, column = _parts(linked, right is None)
            top[left] = left[row]
            if right is not None:
                links[right] += linked.T @ size[left]
                top[right[column >= 0]] = left[column[column >= 0]]
        return pa.table({"node": pa.array(node, pa.binary()), "links": links, "top": pa.array([node[t] for t in top.tolist()], pa.binary())})

    return run


def _digest() -> Column:
    return F.xxhash64(F.coalesce(F.col("text").cast("string"), F.lit("")))


def _block_pairs(blocks: Column, block: Column) -> Column:
    """The pairs (i, j) of blocks, i <= j, that a row of one block is needed for."""
    pair = lambda x: F.struct(F.least(x, block).cast("int").alias("i"), F.greatest(x, block).cast("int").alias("j"))
    return F.transform(F.sequence(F.lit(0), blocks - 1), pair)


def _candidates(classes: DataFrame, depth: int, trees: int, subtree: int) -> DataFrame:
    """Edges (a, b) that join classes of candidate groups."""
    places = classes.select("node", F.posexplode("keys").alias("tree", "key"))
    places = places.select("node", "key", F.xxhash64("tree", F.shiftrightunsigned("key", 8 * (LEVELS - depth))).alias("prefix"))
    shared = places.groupBy("prefix").agg(F.count(F.lit(1)).alias("n")).filter("n > 1")
    met = places.join(shared, "prefix")
    sketch = F.slice("keys", 1, min(trees, SKETCH // LEVELS))
    drawn = classes.select("node", "depth", F.aggregate(sketch, F.lit(b"").cast("binary"), lambda s, x: F.concat(s, F.unhex(F.lpad(F.hex(x), 16, "0")))).alias("sketch"))
    blocks = F.ceil(F.col("n") / subtree).cast("int")
    dealt = met.join(drawn, "node").withColumn("blocks", blocks).withColumn("block", F.pmod(F.xxhash64("node", F.lit("subtree")), F.col("blocks")).cast("int"))
    dealt = dealt.withColumn("meet", F.explode(_block_pairs(F.col("blocks"), F.col("block")))).select("prefix", F.col("meet.i").alias("i"), F.col("meet.j").alias("j"), "key", "depth", "block", "node", "sketch")
    return map_arrow(dealt.repartition("prefix", "i", "j").sortWithinPartitions("prefix", "i", "j", "key"), _walk, "a binary, b binary")


def _linked(
    docs: DataFrame, k: int = SHINGLE, threshold: tuple[int, int] = THRESHOLD, trees: int = TREES, recall: float = TARGET_RECALL, block: int = BLOCK, subtree: int = SUBTREE
) -> tuple[DataFrame, DataFrame]:
    """(doc_id, digest, node of each document; node, set_class, size, links, component, lead of each class of equal shingle sets).

    lead: the first (has no id, doc_id, digest of the text) of the class's documents.
    """
    texts = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")).withColumn("digest", _digest())
    signed = cut(map_arrow(texts, _sign(k, threshold, trees, recall), "doc_id long, digest long, node binary, depth int, keys array<bigint>"))
    lead = F.min(F.struct(F.col("doc_id").isNull().alias("unnamed"), "doc_id", "digest"))
    classes = signed.groupBy("node").agg(F.min("doc_id").alias("set_class"), F.count(F.lit(1)).alias("size"), F.first("depth").alias("depth"), F.first("keys").alias("keys"), lead.alias("lead"))
    edges = _candidates(classes, forest_depth(threshold[0] / threshold[1], trees, recall), trees, subtree)
    groups = connected_components(edges, "a", "b")
    sizes = groups.groupBy("component").agg(F.count(F.lit(1)).alias("members"))
    candidates = groups.join(sizes, "component").join(classes.select("node", "lead", "size"), "node")
    blocks = F.ceil(F.col("members") / block).cast("int")
    candidates = cut(
        candidates.select("node", "lead", "size", F.col("component").alias("group"), blocks.alias("blocks"), F.pmod(F.xxhash64("node"), blocks).cast("int").alias("block"))
    )
    tasks = max(1, -(-candidates.count() // GROUP_CLASSES))
    named = candidates.withColumns({"own_id": F.coalesce("lead.doc_id", F.lit(0)), "own_null": F.col("lead.unnamed"), "own_digest": F.col("lead.digest")})
    mine = (F.coalesce("doc_id", F.lit(0)) == F.col("own_id")) & (F.col("doc_id").isNull() == F.col("own_null")) & (F.col("digest") == F.col("own_digest"))
    read = texts.join(named, mine).select("text", "node", "size", "group", "blocks", "block")
    sets = map_arrow(read, _collect_sets(k), "node binary, size long, group binary, blocks int, block int, shingles binary")
    alone = F.col("blocks") == 1
    task = F.when(alone, F.pmod(F.xxhash64("group"), F.lit(tasks)).cast("string")).otherwise(F.hex("group"))
    dealt = sets.withColumn("meet", F.explode(_block_pairs(F.col("blocks"), F.col("block")))).select(F.col("meet.i").alias("i"), F.col("meet.j").alias("j"), task.alias("key"), "node", "size", "group", "block", "shingles")
    found = cut(group_arrow(dealt, ["key", "i", "j"], _verify(threshold), "node binary, links long, top binary"))
    parts = connected_components(found.filter("node <> top").select("node", "top"), "node", "top")
    links = found.groupBy("node").agg(F.sum("links").alias("links"))
    told = classes.select("node", "set_class", "size", "lead").join(links, "node", "left").join(parts, "node", "left").withColumn("component", F.coalesce("component", "node"))
    return signed.select("doc_id", "digest", "node"), told


def similar_documents(docs: DataFrame, **options) -> DataFrame:
    """One row a document: doc_id, class_id, n_links, set_class.

    class_id: smallest doc_id of the documents it is linked to, directly or through others;
    n_links: other documents whose similarity reaches the threshold, copies included;
    set_class: smallest doc_id among the documents with the same shingle set.
    """
    signed, told = _linked(docs, **options)
    names = told.groupBy("component").agg(F.min("set_class").alias("class_id"))
    named = told.join(names, "component").select("node", "class_id", "set_class", (F.coalesce("links", F.lit(0)) + F.col("size") - 1).alias("n_links"))
    return signed.join(named, "node").select("doc_id", "class_id", F.col("n_links").cast("long").alias("n_links"), "set_class")


def keep_one_of_each(docs: DataFrame, **options) -> DataFrame:
    """The documents with one kept of every near-duplicate class: that with the smallest doc_id, named ones first.

    Documents are told apart by doc_id and text, so a doc_id that is null or given twice loses no other text.
    """
    _, told = _linked(docs, **options)
    kept = told.groupBy("component").agg(F.min("lead").alias("lead")).select(F.coalesce("lead.doc_id", F.lit(0)).alias("__id"), F.col("lead.unnamed").alias("__null"), F.col("lead.digest").alias("__digest"))
    key = ["__id", "__null", "__digest"]
    doc_id = F.col("doc_id").cast("long")
    # the rows are dealt and sorted by the key once, for the join and for repeated rows
    named = docs.withColumns({"__id": F.coalesce(doc_id, F.lit(0)), "__null": doc_id.isNull(), "__digest": _digest()})
    return named.join(kept.hint("merge"), key, "left_semi").dropDuplicates(key).drop(*key)
