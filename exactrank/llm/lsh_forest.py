"""N-gram Jaccard self-join with a MinHash LSH forest and exact verification.

Every text is its set of five-word shingles; texts with the same set are one node. A node has
``TREES`` labels of ``DEPTH`` min-hashes, one in each prefix trie. Two nodes are compared in a
tree if they share the prefix that is matched there, and how long that is follows the data:

1. A run is what shares a prefix. Matching begins with SHALLOW hashes; a run of more than
   ``LIMIT`` nodes is left to its children, down to DEPTH hashes.
2. A node knows from its prefixes how surely a partner at the threshold has been met:
   1 - product over trees of (1 - 0.8 ** length). Where that is under ``RECALL`` the prefix is
   shortened again to ENOUGH hashes, in the trees where the run is smallest first, until the
   recall is reached (with ENOUGH hashes in all trees it always is).

A run over the limit is dealt out in tiles of two blocks, so no task holds one, and all pairs
of a run are compared by their whole sketches: there is no cap on partners. What passes joins
nodes to candidate classes. A class over the limit is first cut by a prefix filter: of its
nodes' shingles, rarest first, similar sets share one among the first fifth. Within what is
left every pair is verified exactly, in tiles of bounded size, so counts of links are whole even
in dense classes. True classes are the components of verified links.

Hot keys: exact copies are one node from the start; joins on node or component have one row a
key on the other side, so adaptive skew joins may split them; groups are counted by partial
aggregates.

Defined results: a text of one to four words has one shingle, all of them; a text without words
is its own bytes (null: none), so equal ones are copies; repeated rows are copies of each
other; a class without doc_id has a null class_id; an empty table gives no rows; columns
besides doc_id and text are ignored (``one_of_each_class`` keeps them, whatever their names).
"""

from __future__ import annotations

import math
from collections.abc import Iterator, Sequence

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from exactrank.llm.common import discard, documents, materialise, own_name
from exactrank.llm.components import components
from exactrank.llm.textkernel import SpanHash, in_window, mix, ngram_hash, owner, pieces, text_buffer, word_bounds

SHINGLE = 5
#: Similarity from which texts are linked, in tenths, so that comparisons are exact.
TENTHS = 8
TREES, DEPTH = 20, 6
#: Where matching begins, and to what it is shortened again.
SHALLOW, ENOUGH = 3, 4
RECALL = 0.9999
#: Nodes of a run that are compared whole; a larger run is left to its children.
LIMIT = 512
#: Run keys (16 bytes each) that are broadcast at most; more of them are joined by exchange.
BROADCAST_KEYS = 200_000
#: Rows of a batch of shingles, about.
SHINGLE_ROWS = 50_000
#: A sketch has 4 bits of each min-hash. Pairs under this estimate are not candidates: five
#: standard errors below the threshold.
LEAST_ESTIMATE = 0.62
#: Nodes of a class in one tile of the verification at most, about.
TILE = 1024

_rng = np.random.default_rng(20240229)
_FACTORS = _rng.integers(1, 1 << 63, TREES * DEPTH, dtype=np.uint64) * np.uint64(2) + np.uint64(1)
_SKETCH_BYTES = -(-TREES * DEPTH // 16) * 8


def surely_met(lengths: Sequence[int], similarity: float = TENTHS / 10) -> float:
    """The probability that a pair of that similarity shares the prefix of some tree."""
    return 1 - math.prod(1 - similarity**k for k in lengths)


def shingles(data: np.ndarray, offs: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Distinct 64-bit shingle hashes of each text, sorted by text, and where each text's begin."""
    spans = SpanHash(data)
    starts, ends, cuts = word_bounds(data, offs)
    words, rows = spans(starts, ends), owner(cuts)
    inside = in_window(rows, SHINGLE)
    hashes, of = [ngram_hash(words, SHINGLE)[inside]], [rows[: len(inside)][inside]]
    count = np.diff(cuts)
    for n in range(1, SHINGLE):
        short = np.flatnonzero(count == n)
        if len(short):
            part = np.concatenate([words[cuts[i] : cuts[i] + n] for i in short])
            hashes.append(ngram_hash(part, n)[::n] + np.uint64(n))
            of.append(short)
    bare = np.flatnonzero(count == 0)
    hashes.append(spans(offs[bare], offs[bare + 1]) ^ np.uint64(0x5BD1E995))
    of.append(bare)
    h, r = np.concatenate(hashes), np.concatenate(of)
    order = np.lexsort((h, r))
    h, r = h[order], r[order]
    fresh = np.ones(len(h), bool)
    fresh[1:] = (h[1:] != h[:-1]) | (r[1:] != r[:-1])
    return h[fresh], np.searchsorted(r[fresh], np.arange(len(offs)))


def node_names(h: np.ndarray, cuts: np.ndarray) -> list[bytes]:
    """128-bit names of the sets: sums of mixed hashes, so the order of a set is irrelevant."""
    x, y = (np.add.reduceat(mix(h ^ np.uint64(s)), cuts[:-1]) if len(cuts) > 1 else np.zeros(0, np.uint64) for s in (0x1F83D9AB, 0x5BE0CD19))
    both = np.stack([x, y], 1).astype(">u8").tobytes()
    return [both[i : i + 16] for i in range(0, len(both), 16)]


def min_hashes(h: np.ndarray, cuts: np.ndarray) -> np.ndarray:
    """One row of TREES * DEPTH min-hashes (32 bits) for each set."""
    out = np.empty((len(cuts) - 1, len(_FACTORS)), np.uint32)
    high = mix(h)
    for j, f in enumerate(_FACTORS):
        out[:, j] = np.minimum.reduceat((high * f) >> np.uint64(32), cuts[:-1])
    return out


def sketch_of(signatures: np.ndarray) -> np.ndarray:
    """The lowest 4 bits of each min-hash, packed; whole 64-bit words."""
    low = (signatures & 15).astype(np.uint8)
    out = np.zeros((len(low), _SKETCH_BYTES), np.uint8)
    out[:, : low.shape[1] // 2] = low[:, ::2] << 4 | low[:, 1::2]
    return out


def _sketch_rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        names, sigs, low = [], [], []
        data, offs = text_buffer(batch["text"])
        for _, _, part, cut in pieces(data, offs):
            h, cuts = shingles(part, cut)
            names += node_names(h, cuts)
            found = min_hashes(h, cuts)
            for table, rows in ((found.astype(">u4").view(np.uint8).reshape(len(found), -1), sigs), (sketch_of(found), low)):
                raw, width = table.tobytes(), table.shape[1]
                rows += [raw[i : i + width] for i in range(0, len(raw), width)]
        yield pa.RecordBatch.from_arrays([batch["doc_id"], batch["rk"], *(pa.array(x, pa.binary()) for x in (names, sigs, low))], ["doc_id", "rk", "node", "sig", "sketch"])


def _run_key(tree: Column, depth: int) -> Column:
    """64 bits for the first ``depth`` hashes of a tree's label."""
    return F.xxhash64(tree, F.lit(depth), F.substring(F.col("sig"), tree * (4 * DEPTH) + 1, F.lit(4 * depth)))


_KEYS = [f"k{d}" for d in range(SHALLOW, DEPTH + 1)]


def _places(nodes: DataFrame, *columns: str) -> DataFrame:
    """A row for each node and tree, with the keys of its runs from SHALLOW to DEPTH hashes."""
    trees = nodes.select(*columns, "sig", F.explode(F.sequence(F.lit(0), F.lit(TREES - 1))).alias("tree"))
    return trees.select(*columns, "tree", *[_run_key(F.col("tree"), d).alias(k) for d, k in enumerate(_KEYS, SHALLOW)])


def _sized(df: DataFrame) -> DataFrame:
    """Broadcast, if the number of rows (a stored table's) allows it."""
    return F.broadcast(df) if df.count() <= BROADCAST_KEYS else df


def crowded_runs(nodes: DataFrame, limit: int) -> DataFrame:
    """(key, n) of every run of more than ``limit`` nodes, at all lengths. Only children of
    crowded runs are counted."""
    found, parents = None, None
    for d, k in enumerate(_KEYS, SHALLOW):
        rows = _places(nodes)
        if parents is not None:
            rows = rows.join(parents.select(F.col("key").alias(_KEYS[d - SHALLOW - 1])), _KEYS[d - SHALLOW - 1], "left_semi")
        level = materialise(rows.groupBy(F.col(k).alias("key")).agg(F.count("*").alias("n")).where(F.col("n") > limit), "crowded")
        found = level if found is None else found.unionByName(level)
        parents = _sized(level)
        if not level.limit(1).count():
            break
    return materialise(found, "crowded")


def matched_prefixes(nodes: DataFrame, limit: int, recall: float = RECALL) -> DataFrame:
    """(node, sketch, tree, key, depth, n): for each node and tree the prefix that is matched, and the
    size of its run where that is over the limit (else null)."""
    crowded = crowded_runs(nodes, limit)
    rows = _places(nodes, "node", "sketch")
    sized = _sized(crowded)
    for k in _KEYS:
        rows = rows.join(sized.select(F.col("key").alias(k), F.col("n").alias("n" + k)), k, "left")
    depth, key, n = F.lit(DEPTH), F.col(_KEYS[-1]), F.col("n" + _KEYS[-1])
    for d, k in reversed(list(enumerate(_KEYS[:-1], SHALLOW))):
        own = F.col("n" + k).isNull()
        depth, key, n = F.when(own, d).otherwise(depth), F.when(own, F.col(k)).otherwise(key), F.when(~own, n)
    rows = rows.withColumn("depth", depth).withColumn("key", key).withColumn("n", n)

    # Nodes that are too deep in too many trees go up again, where that costs least.
    miss = {d: math.log(1 - (TENTHS / 10) ** d) for d in range(SHALLOW, DEPTH + 1)}
    surplus = math.log(1 - recall) - TREES * miss[SHALLOW]
    lost = F.lit(0.0)
    gain = F.lit(0.0)
    for d in range(SHALLOW + 1, DEPTH + 1):
        lost = F.when(F.col("depth") == d, miss[d] - miss[SHALLOW]).otherwise(lost)
        if d > ENOUGH:
            gain = F.when(F.col("depth") == d, miss[d] - miss[ENOUGH]).otherwise(gain)
    up, n_up = f"k{ENOUGH}", f"nk{ENOUGH}"
    deep = rows.where(F.col("depth") > SHALLOW).select("node", "tree", F.col(up).alias("up"), F.col(n_up).alias("cost"), lost.alias("lost"), gain.alias("gain"))
    own = Window.partitionBy("node")
    before = own.orderBy("cost", "tree").rowsBetween(Window.unboundedPreceding, -1)
    order = deep.withColumn("short", F.sum("lost").over(own) - surplus).where("short > 0 AND gain > 0").withColumn("had", F.coalesce(F.sum("gain").over(before), F.lit(0.0)))
    raised = materialise(order.where("had < short").select(F.col("up").alias("key"), "cost").distinct(), "raised")
    rows = rows.join(_sized(raised).select(F.col("key").alias(up), F.col("cost").alias("n_raised")), up, "left")
    back = F.col("n_raised").isNotNull()
    return rows.select(
        "node", "sketch", "tree", F.when(back, F.col(up)).otherwise(F.col("key")).alias("key"), F.when(back, F.lit(ENOUGH)).otherwise(F.col("depth")).alias("depth"),
        F.coalesce("n_raised", "n").alias("n"),
    )


def _cells(matched: DataFrame, limit: int) -> DataFrame:
    """(cell, block, node, sketch): a run is one cell, or tiles of two of its blocks each."""
    blocks = F.ceil(F.coalesce(F.col("n"), F.lit(1)) / limit).cast("int")
    rows = matched.withColumn("blocks", blocks).withColumn("block", F.pmod(F.xxhash64("node"), F.col("blocks")).cast("int"))
    tiles = F.transform(F.sequence(F.lit(0), F.col("blocks") - 1), lambda j: F.xxhash64("key", F.least("block", j), F.greatest("block", j)))
    cell = F.explode(F.when(F.col("blocks") == 1, F.array("key")).otherwise(tiles))
    return rows.select(cell.alias("cell"), "block", "node", "sketch")


_FIFTEEN = np.uint64(0x1111111111111111)


def _differing(x: np.ndarray, y: np.ndarray) -> np.ndarray:
    """In how many of their 4-bit hashes sketches differ, row by row."""
    z = x ^ y
    z |= z >> np.uint64(1)
    z |= z >> np.uint64(2)
    return np.bitwise_count(z & _FIFTEEN).sum(1)


def _cell_links(cell: np.ndarray, block: np.ndarray, sketch: np.ndarray) -> np.ndarray:
    """For rows by cell: the first row that each is linked to, straight or through others.
    A tile of two blocks compares across them (rows of one block meet in that block's own)."""
    least = LEAST_ESTIMATE + (1 - LEAST_ESTIMATE) / 16
    most = TREES * DEPTH - int(np.floor(least * TREES * DEPTH))
    n = len(cell)
    root = np.arange(n)
    start = np.flatnonzero(np.append(True, cell[1:] != cell[:-1])) if n else root
    size = np.diff(np.append(start, n))
    place = np.arange(n) - np.repeat(start, size)
    mixed = np.repeat(np.minimum.reduceat(block, start) != np.maximum.reduceat(block, start), size) if n else root

    def find(x: int) -> int:
        while root[x] != x:
            root[x] = root[root[x]]
            x = root[x]
        return x

    live = np.flatnonzero(place > 0)
    for d in range(1, int(size.max(initial=1))):
        live = live[place[live] >= d]
        to = live - d
        open_ = (root[live] != root[to]) & (~mixed[live] | (block[live] != block[to]))
        i, j = live[open_], to[open_]
        close = _differing(sketch[i], sketch[j]) <= most
        if close.any():
            for a, b in zip(i[close].tolist(), j[close].tolist()):
                x, y = sorted((find(a), find(b)))
                root[y] = x
            while (root[root] != root).any():
                root = root[root]
    return root


def _compare_cells(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Candidate links, as stars, of rows that come by cell."""
    held: pa.Table | None = None

    def links(table: pa.Table) -> pa.RecordBatch:
        cell = table["cell"].to_numpy()
        same = np.zeros(len(cell), bool)
        same[1:] |= cell[1:] == cell[:-1]
        same[:-1] |= cell[1:] == cell[:-1]
        table = table.filter(pa.array(same)).combine_chunks()
        nodes = table["node"].to_pylist()
        sketch = np.frombuffer(b"".join(table["sketch"].to_pylist()), np.uint64).reshape(len(nodes), _SKETCH_BYTES // 8)
        root = _cell_links(table["cell"].to_numpy(), table["block"].to_numpy(), sketch)
        at = np.flatnonzero(root != np.arange(len(root)))
        return pa.RecordBatch.from_arrays([pa.array([nodes[i] for i in root[at]], pa.binary()), pa.array([nodes[i] for i in at], pa.binary())], ["a", "b"])

    for batch in batches:
        table = pa.Table.from_batches([batch])
        held = table if held is None else pa.concat_tables([held, table])
        cell = held["cell"].to_numpy()
        ready = len(cell) - int(np.argmax(cell[::-1] != cell[-1])) if len(cell) and (cell != cell[-1]).any() else 0
        if ready:
            yield links(held.slice(0, ready))
            held = held.slice(ready)
    if held is not None and held.num_rows:
        yield links(held)


def _set_rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        data, offs = text_buffer(batch["text"])
        names, sets = [], []
        for _, _, part, cut in pieces(data, offs):
            h, cuts = shingles(part, cut)
            names += node_names(h, cuts)
            sets += [h[cuts[i] : cuts[i + 1]].tobytes() for i in range(len(cuts) - 1)]
        # A row that only shares the 64-bit row key of the one asked for drops out here.
        meant = pa.array([a == b for a, b in zip(names, batch["node"].to_pylist())])
        made = pa.RecordBatch.from_arrays([*(batch[c] for c in ("component", "node", "copies")), pa.array(sets, pa.binary())], ["component", "node", "copies", "shingles"])
        yield made.filter(meant)


def _verify_tile(tile: pa.Table) -> pa.Table:
    """All pairs of one tile (of one block with itself, or of two): links by node, weighted by
    copies, and a forest that connects what is linked."""
    nodes, copies, block = tile["node"].to_pylist(), tile["copies"].to_numpy(), tile["block"].to_numpy()
    order = sorted(range(len(nodes)), key=lambda i: nodes[i])
    nodes, copies, block = [nodes[i] for i in order], copies[order], block[order]
    sets = [np.frombuffer(s, np.uint64) for s in tile["shingles"].to_pylist()]
    sets = [sets[i] for i in order]
    n, mixed = len(nodes), block.min() != block.max()
    size = np.array([len(s) for s in sets])
    _, code = np.unique(np.concatenate(sets), return_inverse=True)
    member = np.repeat(np.arange(n), size)
    by = np.argsort(code, kind="stable")
    posted = member[by]
    first = np.searchsorted(code[by], np.arange(code.max() + 2))
    cuts = np.concatenate([[0], np.cumsum(size)])
    links, root = np.zeros(n, np.int64), np.arange(n)

    def find(x: int) -> int:
        while root[x] != x:
            root[x] = root[root[x]]
            x = root[x]
        return x

    for i in range(n):
        own = code[cuts[i] : cuts[i + 1]]
        length = first[own + 1] - first[own]
        reach = np.repeat(first[own] - np.concatenate([[0], np.cumsum(length)[:-1]]), length) + np.arange(length.sum())
        common = np.bincount(posted[reach], minlength=n)
        near = 10 * common >= TENTHS * (size[i] + size - common)
        near[i] = False
        if mixed:
            near &= block != block[i]
        found = np.flatnonzero(near)
        links[i] = copies[found].sum()
        for j in found[found > i]:
            a, b = sorted((find(i), find(int(j))))
            root[b] = a
    top = [nodes[find(i)] for i in range(n)]
    return pa.table({"node": pa.array(nodes, pa.binary()), "top": pa.array(top, pa.binary()), "links": pa.array(links)})


def _shingle_rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """A row for each shingle of each set, with how many of them, rarest first, must hold one
    that a similar set has too."""
    for batch in batches:
        size = np.diff(text_buffer(batch["shingles"])[1]) // 8
        lo = 0
        while lo < len(size):
            # Some sets at a time: a batch of thousands makes millions of rows.
            hi = max(lo + 1, int(np.searchsorted(np.cumsum(size[lo:]), SHINGLE_ROWS)) + lo)
            part, own = batch.slice(lo, hi - lo), size[lo:hi]
            of = pa.array(np.repeat(np.arange(hi - lo), own))
            shingle = text_buffer(part["shingles"])[0].view(np.int64)
            enough = np.repeat(own - -(-TENTHS * own // 10) + 1, own)
            yield pa.RecordBatch.from_arrays([part["component"].take(of), part["node"].take(of), pa.array(shingle), pa.array(enough)], ["component", "node", "shingle", "enough"])
            lo = hi


def cut_by_rare_shingles(sets: DataFrame) -> DataFrame:
    """(node, component): large candidate classes ``sets(component, node, shingles)`` cut into those
    whose nodes share rare shingles; nodes that share none drop out. Exact: sets similar to a
    share t miss at most 1 - t of each other, so whatever the order of shingles, one of the first
    |x| - ceil(t |x|) + 1 is in both; rarest first, what a crowd shares plays no part."""
    rows = sets.mapInArrow(_shingle_rows, "component binary, node binary, shingle long, enough long")
    often = rows.groupBy("component", "shingle").agg(F.count("*").alias("n"))
    nth = F.row_number().over(Window.partitionBy("node").orderBy("n", "shingle"))
    first = rows.join(often, ["component", "shingle"]).withColumn("nth", nth).where("nth <= enough AND n > 1").select("component", "shingle", "node")
    first = materialise(first, "rare")
    tops = first.groupBy("component", "shingle").agg(F.min("node").alias("top"))
    return components(first.join(tops, ["component", "shingle"]).where("node <> top").select(F.col("top").alias("a"), F.col("node").alias("b")))


def candidate_links(nodes: DataFrame, limit: int) -> DataFrame:
    """Stars (a, b) that join all nodes of ``nodes(node, sig, sketch)`` that may be similar."""
    cells = _cells(matched_prefixes(nodes, limit), limit)
    return cells.repartition("cell").sortWithinPartitions("cell").mapInArrow(_compare_cells, "a binary, b binary").distinct()


def near_duplicates(docs: DataFrame, limit: int | None = None) -> DataFrame:
    """doc_id, rk (row key), class_id (least doc_id of the class) and n_links (other documents
    that are similar) for each row of ``docs(doc_id, text)``."""
    rk = F.xxhash64("doc_id", F.coalesce(F.col("text"), F.lit("")))
    docs = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.coalesce("text", F.lit("")).alias("text")).withColumn("rk", rk)
    made = materialise(docs.mapInArrow(_sketch_rows, "doc_id long, rk long, node binary, sig binary, sketch binary"), "sketches")
    nodes = materialise(made.groupBy("node").agg(F.first("sig").alias("sig"), F.first("sketch").alias("sketch")), "distinct")
    rows = made.select("doc_id", "rk", "node")
    candidates = components(candidate_links(nodes, limit or LIMIT))
    discard(nodes)

    # Exact verification within candidate classes, one row of each node standing for its copies.
    stand_in = rows.groupBy("node").agg(F.min(F.struct(F.col("doc_id").isNull(), "doc_id", "rk"))["rk"].alias("rk"), F.count("*").alias("copies"))
    wanted = candidates.join(stand_in, "node")
    sets = docs.join(wanted, "rk").select("text", "component", "node", "copies").mapInArrow(_set_rows, "component binary, node binary, copies long, shingles binary")
    sets = materialise(sets.dropDuplicates(["node"]), "sets")
    sizes = candidates.groupBy("component").count()
    large = materialise(sizes.where(F.col("count") > TILE).select("component"), "large")
    if large.limit(1).count():
        finer = cut_by_rare_shingles(sets.join(_sized(large), "component", "left_semi"))
        calm = candidates.join(_sized(large), "component", "left_anti")
        candidates = materialise(calm.unionByName(finer), "candidates")
        sizes = candidates.groupBy("component").count()
        # A class's own name may have gone to a part of it, so sets take the new ones by node.
        sets = sets.drop("component").join(candidates, "node")
    tiled = sizes.select("component", F.ceil(F.col("count") / TILE).cast("int").alias("blocks"))
    sets = sets.join(tiled, "component").withColumn("block", F.pmod(F.xxhash64("node"), F.col("blocks")).cast("int"))
    # A block meets each block of its class once: tile (i, j) with i <= j.
    tiles = F.transform(F.sequence(F.lit(0), F.col("blocks") - 1), lambda j: F.struct(F.least("block", j).alias("i"), F.greatest("block", j).alias("j")))
    dealt = sets.withColumn("tile", F.explode(tiles)).select("component", "tile.i", "tile.j", "node", "copies", "block", "shingles")
    verified = materialise(dealt.groupBy("component", "i", "j").applyInArrow(_verify_tile, "node binary, top binary, links long"), "verified")
    links = verified.groupBy("node").agg(F.sum("links").alias("links"))
    classes = components(verified.where("node <> top").select(F.col("top").alias("a"), F.col("node").alias("b")))

    by_node = (
        rows.groupBy("node").agg(F.min("doc_id").alias("least"), F.count("*").alias("copies"))
        .join(classes, "node", "left").join(links, "node", "left")
        .select("node", F.coalesce("component", "node").alias("component"), "least", (F.coalesce("links", F.lit(0)) + F.col("copies") - 1).alias("n_links"))
    )
    by_node = materialise(by_node, "nodes")
    named = by_node.groupBy("component").agg(F.min("least").alias("class_id"))
    result = by_node.join(named, "component").select("node", "component", "class_id", "n_links")
    return rows.join(result, "node").select("doc_id", "rk", "component", "class_id", "n_links")


def one_of_each_class(docs: DataFrame) -> DataFrame:
    """The rows of ``docs`` (all columns) that stay: the least doc_id of each class, once."""
    found = near_duplicates(docs.select("doc_id", "text"))
    rk, last = own_name(docs, "rk"), own_name(docs, "last")
    first = found.groupBy("component").agg(F.min(F.struct(F.col("doc_id").isNull().alias("last"), "doc_id", "rk")).alias("one"))
    # The id beside the 64-bit key: rows that only share the key are not each other's.
    first = first.select(F.col("one.doc_id").alias(last), F.col("one.rk").alias(rk))
    keyed = docs.withColumn(rk, F.xxhash64(F.col("doc_id").cast("long"), F.coalesce(F.col("text"), F.lit(""))))
    kept = keyed.join(first, (keyed[rk] == first[rk]) & F.col("doc_id").cast("long").eqNullSafe(F.col(last))).drop(first[rk])
    return kept.dropDuplicates([rk, "doc_id"]).select(*docs.columns)


def op4_lsh_forest_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_duplicates(documents(spark, sf_dir, "doc_id", "text")).select("doc_id", "class_id", "n_links")


OP4_SQL = rf"""
WITH RECURSIVE d AS (SELECT row_number() OVER () AS rid, doc_id, coalesce(text, '') AS text,
  list_filter(regexp_split_to_array(coalesce(text, ''), '[\x20\x09-\x0D]+'), lambda x: x <> '') AS w FROM documents),
s AS (SELECT DISTINCT rid, unnest(CASE
    WHEN len(w) = 0 THEN ['bare ' || text]
    WHEN len(w) < {SHINGLE} THEN [len(w) || ' ' || array_to_string(w, ' ')]
    ELSE list_transform(range(1, len(w) - {SHINGLE - 2}), lambda i: array_to_string(w[i:i + {SHINGLE - 1}], ' ')) END) AS g FROM d),
n AS (SELECT rid, count(*) AS n FROM s GROUP BY rid),
p AS (SELECT a.rid AS a, b.rid AS b, count(*) AS c FROM s a JOIN s b ON a.g = b.g AND a.rid <> b.rid GROUP BY ALL),
l AS (SELECT a, b FROM p JOIN n x ON x.rid = a JOIN n y ON y.rid = b WHERE 10 * c >= {TENTHS} * (x.n + y.n - c)),
r(a, b) AS (SELECT a, b FROM l UNION SELECT r.a, l.b FROM r JOIN l ON r.b = l.a)
SELECT d.doc_id,
  (SELECT min(e.doc_id) FROM d e WHERE e.rid = d.rid OR e.rid IN (SELECT b FROM r WHERE r.a = d.rid)) AS class_id,
  (SELECT count(*) FROM l WHERE l.a = d.rid)::BIGINT AS n_links
FROM d
"""
