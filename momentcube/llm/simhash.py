"""SimHash near-duplicates through an inverted index over byte positions with count filtering.

Fingerprints at most r bits apart differ in at most r bytes, so of B positional bytes at least B - r are equal:
the guaranteed minimum of the tally. Lists of single bytes would hold 1/256 of all rows each, so the index is
keyed by *sets* of positional bytes: two fingerprints meet under a key exactly when the tally reaches its size.

* 64 bits, r = 2: keys are all C(8,6) = 28 sets of six positional bytes, which is the guaranteed minimum itself.
  A list fixes 48 bits, so it holds at most 65,536 different fingerprints whatever the input, and its
  links are looked up in a table of the 16 bits left, 137 probes for each fingerprint: linear, no pairs are emitted.
* ``near_duplicate_classes`` (five-word shingles, similarity 0.8): wider radius, see there.

Equal fingerprints are one class from the start. Null and empty texts have fingerprint zero and link like any other.
Repeated rows give repeated output rows; a null doc_id keeps its row and its component is the smallest known id.
"""

from __future__ import annotations

from itertools import accumulate, combinations

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, functions as F, types as T

from .common import BLOCK, bound_batches, components, give_back, local_roots, map_rows, materialize, release

BYTE_SETS = [m for m in (sum(0xFF << (8 * i) for i in s) for s in combinations(range(8), 6))]
_TWO = [s for s in combinations(range(8), 2)]
_FLIPS = np.array([0] + [1 << i for i in range(16)] + [(1 << i) | (1 << j) for i in range(16) for j in range(i)], dtype=np.uint32)


def shingle_hashes(text: str | None, width: int, seed: int = 42) -> np.ndarray:
    """XXH64 of every shingle of ``width`` words (ASCII white space splits, ASCII capitals folded), repeats included."""
    words = (text or "").encode().lower().split()
    if not words:
        return np.empty(0, dtype=np.uint64)
    joined = b" ".join(words)
    if len(words) <= width:
        return np.array([xxhash.xxh64_intdigest(joined, seed)], dtype=np.uint64)
    ends = list(accumulate(len(w) + 1 for w in words))
    h = xxhash.xxh64_intdigest
    spans = zip([0, *ends], ends[width - 1 :])
    return np.fromiter((h(joined[a : b - 1], seed) for a, b in spans), dtype=np.uint64, count=len(words) - width + 1)


def bit_counts(h: np.ndarray, chunk: int = 1 << 16) -> np.ndarray:
    total = np.zeros(64, dtype=np.int64)
    for i in range(0, len(h), chunk):
        bits = np.unpackbits(h[i : i + chunk].view(np.uint8).reshape(-1, 8), axis=1, bitorder="little")
        for j in range(0, len(bits), 255):
            total += bits[j : j + 255].sum(axis=0, dtype=np.uint8)
    return total


def fingerprint64(text: str | None, width: int = 3) -> int:
    h = shingle_hashes(text, width)
    if not len(h):
        return 0
    return int(np.packbits(bit_counts(h) * 2 > len(h), bitorder="little").view(np.uint64)[0])


def fingerprints(docs: DataFrame, width: int = 3) -> DataFrame:
    """doc_id, fp (the 64 bits as a long)."""

    def add(batch):
        col = batch.column(batch.schema.get_field_index("text")).to_pylist()
        return {"fp": np.array([fingerprint64(t, width) for t in col], dtype=np.uint64).view(np.int64)}

    return map_rows(docs.select("doc_id", "text"), add, [T.StructField("fp", T.LongType())], keep=["doc_id"])


def _list_edges(values: np.ndarray, which: int) -> tuple[np.ndarray, np.ndarray]:
    """Spanning edges of the links (two bits or fewer) inside one list."""
    n = len(values)
    if n <= 64:
        root = local_roots(np.bitwise_count(values[:, None] ^ values[None, :]) <= 2)
    else:
        left = [i for i in range(8) if not (BYTE_SETS[which] >> (8 * i)) & 0xFF]
        rest = (((values >> np.uint64(8 * left[0])) & np.uint64(255)) | (((values >> np.uint64(8 * left[1])) & np.uint64(255)) << np.uint64(8))).astype(np.int64)
        table = np.full(1 << 16, -1, dtype=np.int64)
        table[rest] = np.arange(n)
        root = np.arange(n)
        while True:
            low = root.copy()
            for flip in _FLIPS.astype(np.int64):
                other = table[rest ^ flip]
                np.minimum(low, np.where(other >= 0, root[other], n), out=low)
            low = low[low]
            if (low == root).all():
                break
            root = low
    moved = np.nonzero(root != np.arange(n))[0]
    return values[moved], values[root[moved]]


def fingerprint_links(distinct: DataFrame) -> DataFrame:
    """Edges (u, v) between different fingerprints of ``distinct(fp)`` that span the links of two bits or fewer."""
    signed = [m - (1 << 64) if m >> 63 else m for m in BYTE_SETS]
    keys = F.array(*[F.struct(F.lit(i).alias("which"), F.col("fp").bitwiseAND(F.lit(m)).alias("key")) for i, m in enumerate(signed)])
    lists = distinct.select("fp", F.explode(keys).alias("k")).groupBy("k.which", "k.key").agg(F.collect_list("fp").alias("fps")).where(F.size("fps") > 1)

    def run(batches):
        for batch in batches:
            which, fps = batch.column(0).to_pylist(), batch.column(2)
            for i, w in enumerate(which):
                values = np.unique(np.asarray(fps[i].values.to_numpy(zero_copy_only=False), dtype=np.int64)).view(np.uint64)
                u, v = _list_edges(values, w)
                if len(u):
                    yield pa.RecordBatch.from_arrays([pa.array(u.view(np.int64)), pa.array(v.view(np.int64))], names=["u", "v"])

    return lists.mapInArrow(run, "u long, v long")


def fingerprint_classes(docs: DataFrame, width: int = 3) -> DataFrame:
    """doc_id, fingerprint (16 hex digits), component_id."""
    prints = materialize(fingerprints(docs, width))
    distinct = materialize(prints.groupBy("fp").agg(F.min("doc_id").alias("first")))
    roots = materialize(components(fingerprint_links(distinct.select("fp"))))
    placed = distinct.join(roots.toDF("fp", "root"), "fp", "left").select("fp", "first", F.coalesce("root", "fp").alias("root"))
    least = placed.groupBy("root").agg(F.min("first").alias("component_id"))
    known = placed.join(least, "root").select("fp", "component_id")
    return prints.join(known, "fp").select("doc_id", F.lpad(F.lower(F.hex("fp")), 16, "0").alias("fingerprint"), "component_id")


# Five-word shingles, similarity 0.8: wide fingerprints -------------------------------------------------------------

WIDE_WORDS = 4
_SPREAD = (np.arange(1, WIDE_WORDS + 1, dtype=np.uint64) * np.uint64(0x9E3779B97F4A7C15)) | np.uint64(1)


def wide_fingerprint(h: np.ndarray) -> np.ndarray:
    """256 bits as four words: four remixed copies of each shingle's hash, majority by bit."""
    out = np.zeros(WIDE_WORDS, dtype=np.uint64)
    for k in range(WIDE_WORDS):
        x = (h ^ _SPREAD[k]) * np.uint64(0xBF58476D1CE4E5B9)
        x = (x ^ (x >> np.uint64(29))) * np.uint64(0x94D049BB133111EB)
        x ^= x >> np.uint64(32)
        if len(x):
            out[k] = np.packbits(bit_counts(x) * 2 > len(x), bitorder="little").view(np.uint64)[0]
    return out


def max_bits(similarity: float, bits: int = 64 * WIDE_WORDS, deviations: float = 6.0) -> int:
    """Bits by which fingerprints of shingle sets with this Jaccard similarity differ in expectation, plus so many deviations.

    Sets of few shingles differ by more than the expected share of many (0.19 for four within five, against 0.15 at 0.8); six
    deviations of the latter are four of theirs.
    """
    cosine = 2 * similarity / (1 + similarity)
    share = np.arccos(cosine) / np.pi
    return int(bits * share + deviations * np.sqrt(bits * share * (1 - share)))


def index_keys(distinct: np.ndarray, similarity: float) -> np.ndarray:
    """The least of a sorted set of shingle hashes, so many that two sets with this Jaccard similarity share one of them.

    Such sets share at least ``similarity`` of either, so they cannot differ on as many of either's least hashes.
    """
    n = len(distinct)
    return distinct[: n - int(np.ceil(similarity * n - 1e-9)) + 1] if n else distinct


#: Least keys of a node that show whether two nodes met in an earlier list.
HEAD = 8
#: Distance of what may not link.
NO_LINK = np.uint16(65535)


def _nearest_forest(far: np.ndarray, tie: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Ends of the edges of the minimum spanning forest of one block. ``far`` and ``tie`` are symmetric; far is NO_LINK where nothing may link.

    Ties go by ``tie``, so blocks that hold the same links give the same edges.
    """
    n = len(far)
    none = np.uint32(NO_LINK) << np.uint32(16)
    cost = np.where(far == NO_LINK, none, (far.astype(np.uint32) << np.uint32(16)) | tie)
    a, b = [], []
    best, origin, open_ = np.full(n, none, dtype=np.uint32), np.zeros(n, dtype=np.int64), np.ones(n, dtype=bool)
    i = 0
    for _ in range(n - 1):
        open_[i] = False
        best[i] = none
        nearer = open_ & (cost[i] < best)
        best[nearer], origin[nearer] = cost[i][nearer], i
        j = int(best.argmin())
        if best[j] == none:
            j = int(open_.argmax())
        else:
            a.append(int(origin[j])), b.append(j)
        i = j
    return np.array(a, dtype=np.int64), np.array(b, dtype=np.int64)


def _lists(prints: DataFrame) -> DataFrame:
    """(list, ci, cj, chunk, node, before) of nodes that share a key, dealt to pairs of chunks.

    ``before`` is the node's key next below the list's. Two nodes with the same key below met there already, so a list in
    which all have the same is gone; the least key has the node itself below it.
    """
    below = F.concat(F.array("node"), F.slice("keys", 1, F.size("keys") - 1))
    each = prints.where(F.size("keys") > 0).select("node", F.explode(F.arrays_zip(F.col("keys").alias("key"), below.alias("before"))).alias("k"))
    lists = each.groupBy(F.col("k.key").alias("list")).agg(F.collect_set(F.struct("node", F.col("k.before").alias("before"))).alias("rows"))
    lists = lists.where((F.size("rows") > 1) & (F.array_min("rows.before") < F.array_max("rows.before")))
    parts = F.ceil(F.size("rows") / F.lit(BLOCK)).cast("int")
    rows = lists.select("list", parts.alias("parts"), F.explode("rows").alias("r")).select("list", "parts", "r.node", "r.before")
    rows = rows.withColumn("chunk", F.pmod(F.xxhash64("node"), "parts").cast("int"))
    rows = rows.withColumn("other", F.explode(F.sequence(F.lit(0), F.col("parts") - 1)))
    return rows.select("list", F.least("chunk", "other").alias("ci"), F.greatest("chunk", "other").alias("cj"), "chunk", "node", "before")


def _distances(fp: np.ndarray, n: np.ndarray, root: np.ndarray, similarity: float) -> np.ndarray:
    """Bits by which fingerprints of one block differ; NO_LINK within a class and where size or fingerprint rule the similarity out."""
    far = np.zeros((len(fp), len(fp)), dtype=np.uint16)
    for k in range(WIDE_WORDS):
        far += np.bitwise_count(fp[:, None, k] ^ fp[None, :, k])
    far[far > max_bits(similarity)] = NO_LINK
    far[n[:, None] < similarity * n[None, :] - 1e-9] = NO_LINK
    far[n[None, :] < similarity * n[:, None] - 1e-9] = NO_LINK
    far[root[:, None] == root[None, :]] = NO_LINK
    return far


def _unlink_met(far: np.ndarray, heads: list[bytes], at: int) -> None:
    """NO_LINK for nodes that share one of their least keys (``heads``) below ``at``: they meet in that key's list."""
    keys = np.frombuffer(b"".join(heads), dtype=np.uint64)
    owner = np.repeat(np.arange(len(heads)), [len(h) // 8 for h in heads])
    owner, keys = owner[keys < at], keys[keys < at]
    order = np.argsort(keys, kind="stable")
    owner, keys = owner[order], keys[order]
    cuts = np.concatenate([[0], np.nonzero(keys[1:] != keys[:-1])[0] + 1, [len(keys)]])
    for i in np.nonzero(np.diff(cuts) > 1)[0]:
        same = owner[cuts[i] : cuts[i + 1]]
        far[np.ix_(same, same)] = NO_LINK


def _blocks(lists: DataFrame, nodes: DataFrame, columns: list[str]) -> DataFrame:
    blocks = lists.join(nodes.select("node", "root", "n", "proof_fp", *columns), "node")
    return blocks.repartition("list", "ci", "cj").sortWithinPartitions("list", "ci", "cj", "node")


def _block_distances(rows: pa.Table, similarity: float) -> np.ndarray:
    root, n, before, chunk = (rows.column(c).to_numpy() for c in ("root", "n", "before", "chunk"))
    far = _distances(np.frombuffer(b"".join(rows.column("proof_fp").to_pylist()), dtype=np.uint64).reshape(-1, WIDE_WORDS), n, root, similarity)
    far[before[:, None] == before[None, :]] = NO_LINK
    if rows.column("ci")[0].as_py() != rows.column("cj")[0].as_py():
        far[chunk[:, None] == chunk[None, :]] = NO_LINK
    return far


def _nearest_links(lists: DataFrame, nodes: DataFrame, similarity: float) -> DataFrame:
    """(u, v, list) of a nearest-first forest of the links of each block of ``lists``, list the least; ``nodes`` has (node, root, n, proof_fp)."""

    def run(batches):
        for rows in contiguous(batches, ["list", "ci", "cj"]):
            if rows.num_rows < 2:
                continue
            node = rows.column("node").to_numpy()
            mixed = node.view(np.uint64) * np.uint64(0x9E3779B97F4A7C15)
            a, b = _nearest_forest(_block_distances(rows, similarity), ((mixed[:, None] ^ mixed[None, :]) >> np.uint64(48)).astype(np.uint32))
            x, y, at_list = node[a], node[b], np.full(len(a), rows.column("list")[0].as_py(), dtype=np.int64)
            yield pa.RecordBatch.from_arrays([pa.array(np.minimum(x, y)), pa.array(np.maximum(x, y)), pa.array(at_list)], names=["u", "v", "list"])

    return _blocks(lists, nodes, []).mapInArrow(run, "u long, v long, list long").groupBy("u", "v").agg(F.min("list").alias("list"))


def _open_nodes(lists: DataFrame, nodes: DataFrame, similarity: float) -> DataFrame:
    """(list, node) of nodes with a link to another class in the list: rows of nodes, whatever number of links they have there.

    A link counts in the list of the least key that its nodes share alone, as far as their ``head`` shows it.
    """

    def run(batches):
        for rows in contiguous(batches, ["list", "ci", "cj"]):
            root = rows.column("root").to_numpy()
            if (root == root[0]).all():
                continue
            far, at = _block_distances(rows, similarity), rows.column("list")[0].as_py()
            if (far != NO_LINK).any():
                _unlink_met(far, rows.column("head").to_pylist(), np.uint64(at % (1 << 64)))
            node = rows.column("node").to_numpy()[(far != NO_LINK).any(axis=1)]
            if len(node):
                yield pa.RecordBatch.from_arrays([pa.array(np.full(len(node), at, dtype=np.int64)), pa.array(node)], names=["list", "node"])

    return _blocks(lists, nodes, ["head"]).mapInArrow(run, "list long, node long").distinct()


#: Cells of one node that meet its text in one task.
HUB = 64
#: Shingles and nodes of one side of a cell.
CELL_SHINGLES, CELL_NODES = 1 << 19, 512


def _cells(links: DataFrame) -> DataFrame:
    """Deal links(u, v, nu, nv, list, ...) to cells (list, ci, cj), pairs of chunks of the list's nodes.

    A text goes to each cell of its links once, not to each link; chunks are bounded by their shingles and nodes.
    """
    ends = links.select("list", F.col("u").alias("node"), F.col("nu").alias("n")).union(links.select("list", "v", "nv")).distinct()
    size = ends.groupBy("list").agg(F.greatest(F.ceil(F.sum("n") / F.lit(CELL_SHINGLES)), F.ceil(F.count(F.lit(1)) / F.lit(CELL_NODES)), F.lit(1)).cast("int").alias("parts"))
    a, b = (F.pmod(F.xxhash64(F.col(c), F.col("list")), F.col("parts")).cast("int") for c in "uv")
    return links.join(size, "list").withColumn("ci", F.least(a, b)).withColumn("cj", F.greatest(a, b)).drop("parts", "nu", "nv")


def _texts(needs: DataFrame, known: DataFrame) -> DataFrame:
    """``needs`` (list, ci, cj, node, ...) with the nodes' texts."""
    # The text of a node of many cells is dealt to one task for each HUB of them. Written first, so that its size is known to the join:
    # few nodes are broadcast and no other text is shuffled.
    parts = materialize(needs.groupBy("node").agg(F.ceil(F.count(F.lit(1)) / F.lit(HUB)).cast("int").alias("parts")))
    salted = known.join(parts, "node").withColumn("salt", F.explode(F.sequence(F.lit(0), F.col("parts") - 1))).drop("parts")
    dealt = needs.join(parts, "node").withColumn("salt", F.pmod(F.xxhash64("list", "ci", "cj"), "parts").cast("int")).drop("parts")
    return dealt.join(salted, ["node", "salt"]).drop("salt")


def _alike(links: DataFrame, known: DataFrame, similarity: float, shingle: int) -> DataFrame:
    """(cu, cv) of links, dealt to cells, whose sets of shingles of both whole texts have this Jaccard similarity.

    A link whose classes are joined already by links proven in its cell is passed over: it would not change the classes.
    """
    cell = ["list", "ci", "cj"]
    needs = links.select(*cell, F.col("u").alias("node")).union(links.select(*cell, F.col("v"))).distinct()
    held = _texts(needs, known).selectExpr(*cell, "node u", "cast(null as long) v", "cast(null as long) cu", "cast(null as long) cv", "text")
    rows = held.union(links.selectExpr(*cell, "u", "v", "cu", "cv", "cast(null as string)"))
    rows = rows.repartition(*cell).sortWithinPartitions(*cell, F.col("v").asc_nulls_first(), "u")
    bound_batches(links.sparkSession)

    def run(batches):
        now, sets, above = None, {}, {}

        def top(x):
            while above.get(x, x) != x:
                above[x] = x = above.get(above[x], above[x])
            return x

        for batch in batches:
            cols = {name: batch.column(i).to_pylist() for i, name in enumerate(batch.schema.names)}
            good: list[tuple[int, int]] = []
            for at, u, v, cu, cv, text in zip(zip(cols["list"], cols["ci"], cols["cj"]), *(cols[c] for c in ("u", "v", "cu", "cv", "text"))):
                if at != now:
                    now, sets, above = at, {}, {}
                if v is None:
                    sets[u] = np.unique(shingle_hashes(text, shingle))
                elif top(cu) != top(cv):
                    x, y = sets[u], sets[v]
                    both = len(np.intersect1d(x, y, assume_unique=True))
                    if both >= similarity * (len(x) + len(y) - both):
                        above[top(cu)] = top(cv)
                        good.append((cu, cv))
            yield pa.RecordBatch.from_arrays([pa.array([g[k] for g in good], type=pa.int64()) for k in (0, 1)], names=["u", "v"])
        give_back()

    return rows.mapInArrow(run, "u long, v long")


def _joined(sets: list[np.ndarray], root: np.ndarray, far: np.ndarray, similarity: float) -> tuple[np.ndarray, np.ndarray]:
    """Roots that links of one cell join, as spanning edges: each link that ``far`` leaves between classes still different is tried on the sets."""
    size = np.array([len(x) for x in sets])
    code = np.split(np.unique(np.concatenate(sets), return_inverse=True)[1], np.cumsum(size)[:-1])
    held = np.zeros(1 + max(int(c.max()) for c in code if len(c)) if size.any() else 1, dtype=bool)
    now, a, b = root.copy(), [], []
    for i in range(len(sets) - 1):
        # A few at a time: classes joined early spare the rest of their links.
        rest = i + 1 + np.nonzero((far[i, i + 1 :] != NO_LINK) & (now[i + 1 :] != now[i]))[0]
        if not len(rest):
            continue
        held[code[i]] = True
        while len(rest):
            part, rest = rest[:64], rest[64:]
            both = np.add.reduceat(np.append(held[np.concatenate([code[j] for j in part])], False).astype(np.int32), np.cumsum(np.append(0, size[part][:-1])))
            both[size[part] == 0] = 0
            for j in part[both >= similarity * (size[i] + size[part] - both)]:
                if now[j] != now[i]:
                    a.append(now[i]), b.append(now[j])
                    now[now == now[j]] = now[i]
            rest = rest[now[rest] != now[i]]
        held[code[i]] = False
    return np.array(a, dtype=np.int64), np.array(b, dtype=np.int64)


def _alike_in_cells(open_nodes: DataFrame, nodes: DataFrame, known: DataFrame, similarity: float, shingle: int) -> DataFrame:
    """(u, v) of roots: spanning edges of all links between ``open_nodes`` (list, node) of a list that the sets of shingles of the whole texts prove.

    The links are no rows: a list's nodes are dealt to cells, pairs of chunks bounded by their shingles and nodes, and tried there.
    """
    cell = ["list", "ci", "cj"]
    sized = open_nodes.join(nodes.select("node", "root", "n", "proof_fp"), "node")
    parts = sized.groupBy("list").agg(F.greatest(F.ceil(F.sum("n") / F.lit(CELL_SHINGLES)), F.ceil(F.count(F.lit(1)) / F.lit(BLOCK)), F.lit(1)).cast("int").alias("parts"))
    dealt = sized.join(parts, "list").withColumn("chunk", F.pmod(F.xxhash64("node", "list"), "parts").cast("int"))
    dealt = dealt.withColumn("other", F.explode(F.sequence(F.lit(0), F.col("parts") - 1)))
    needs = materialize(dealt.select("list", F.least("chunk", "other").alias("ci"), F.greatest("chunk", "other").alias("cj"), "chunk", "node", "root", "n", "proof_fp"))
    rows = _texts(needs, known).select(*cell, "chunk", "node", "root", "n", "proof_fp", "text").repartition(*cell).sortWithinPartitions(*cell, "node")
    bound_batches(open_nodes.sparkSession)

    def proven(at, held):
        chunk, root, n = (np.array([h[k] for h in held]) for k in (0, 1, 2))
        far = _distances(np.frombuffer(b"".join(h[3] for h in held), dtype=np.uint64).reshape(-1, WIDE_WORDS), n, root, similarity)
        if at[1] != at[2]:
            far[chunk[:, None] == chunk[None, :]] = NO_LINK
        u, v = _joined([h[4] for h in held], root, far, similarity)
        return pa.RecordBatch.from_arrays([pa.array(u), pa.array(v)], names=["u", "v"])

    def run(batches):
        now, held = None, []
        for batch in batches:
            cols = {name: batch.column(i).to_pylist() for i, name in enumerate(batch.schema.names)}
            for at, *row, text in zip(zip(*(cols[c] for c in cell)), *(cols[c] for c in ("chunk", "root", "n", "proof_fp", "text"))):
                if at != now:
                    if len(held) > 1:
                        yield proven(now, held)
                    now, held = at, []
                held.append((*row, np.unique(shingle_hashes(text, shingle))))
        if len(held) > 1:
            yield proven(now, held)
        give_back()

    return rows.mapInArrow(run, "u long, v long")


def _proven_classes(lists: DataFrame, nodes: DataFrame, known: DataFrame, similarity: float, shingle: int) -> DataFrame:
    """(node, root) of ``nodes``: classes spanned by the links that the shingles prove.

    First the forests' links are proven, which merges most copies; then every other link between different classes is, so no
    link that meets is left untried. Those are tried where their texts meet and are never listed: their number grows with the
    square of a group's size.
    """
    alone = nodes.withColumn("root", F.col("node"))
    links = _nearest_links(lists, alone, similarity)
    for c in ("u", "v"):
        links = links.join(alone.select("node", "root", "n").toDF(c, f"c{c}", f"n{c}"), c)
    links = materialize(links)
    dealt = materialize(_cells(links))
    release(links)
    merged = materialize(components(_alike(dealt, known, similarity, shingle)))
    root = materialize(nodes.select("node").join(merged.toDF("node", "to"), "node", "left").select("node", F.coalesce("to", "node").alias("root")))
    release(dealt)
    rooted = nodes.join(root, "node")
    open_nodes = materialize(_open_nodes(lists, rooted, similarity))
    merged = materialize(components(_alike_in_cells(open_nodes, rooted, known, similarity, shingle)))
    return materialize(root.join(merged.toDF("root", "to"), "root", "left").select("node", F.coalesce("to", "root").alias("root")))


def _row_key() -> list:
    """Which row of documents: its id and its text; the texts are only hashed."""
    return [F.coalesce(F.col("doc_id").cast("string"), F.lit("")).alias("row_id"), F.xxhash64("text").alias("row_text")]


def _near_duplicates(docs: DataFrame, similarity: float, shingle: int, members: bool) -> tuple[DataFrame | None, DataFrame, DataFrame]:
    """(doc_id, node) of all rows, if ``members``; one row of docs for each node (doc, node, linked); (node, first, least) of linked nodes.

    Work tables that no result reads are deleted as soon as the last step that reads them is written.
    """

    def add(batch):
        col = batch.column(batch.schema.get_field_index("text")).to_pylist()
        sets = [np.unique(shingle_hashes(t, shingle)) for t in col]
        same = [xxhash.xxh3_128_hexdigest(b" ".join((t or "").encode().lower().split())) for t in col]
        return {"same": same, "n": [len(x) for x in sets], "keys": [index_keys(x, similarity).view(np.int64) for x in sets], "head": [index_keys(x, similarity)[:HEAD].tobytes() for x in sets], "proof_fp": [wide_fingerprint(x).tobytes() for x in sets]}

    fields = [T.StructField("same", T.StringType()), T.StructField("n", T.IntegerType()), T.StructField("keys", T.ArrayType(T.LongType())), T.StructField("head", T.BinaryType()), T.StructField("proof_fp", T.BinaryType())]
    keyed = materialize(map_rows(docs.select("doc_id", "text", *_row_key()), add, fields, keep=["doc_id", "row_id", "row_text"]).withColumn("node", F.xxhash64("same")))
    first = F.struct(F.col("doc_id").isNull().alias("unknown"), "doc_id", "row_id", "row_text", "node")
    prints = materialize(keyed.select("doc_id", "node")) if members else None
    distinct = materialize(keyed.groupBy("node").agg(F.min(first).alias("first"), F.first("n").alias("n"), F.first("head").alias("head"), F.first("proof_fp").alias("proof_fp")))
    lists = materialize(_lists(keyed))
    release(keyed)
    linked = lists.select("node").distinct().withColumn("linked", F.lit(True))
    row = distinct.join(linked, "node", "left").select("first.row_id", "first.row_text", "node", F.coalesce("linked", F.lit(False)).alias("linked"))
    # The text is shuffled once, by row: copies of one text are spread.
    whole = docs.select(F.struct(*[docs[c] for c in docs.columns]).alias("doc"), *_row_key())
    one = materialize(whole.join(row, ["row_id", "row_text"]).dropDuplicates(["row_id", "row_text"]).select("doc", "node", "linked"))
    known = one.where("linked").select("node", "doc.text")
    nodes = materialize(distinct.join(linked, "node").select("node", "n", "head", "proof_fp", "first"))
    classes = materialize(nodes.select("node", "first").join(_proven_classes(lists, nodes, known, similarity, shingle), "node"))
    for done in (lists, nodes, distinct):
        release(done)
    least = classes.groupBy("root").agg(F.min("first").alias("least"))
    return prints, one, classes.join(least, "root").select("node", "first", "least")


def near_duplicate_classes(docs: DataFrame, similarity: float = 0.8, shingle: int = 5) -> DataFrame:
    """doc_id, component_id: classes of documents of which shingle sets are ``similarity`` alike or more.

    Equal word sequences form one class first. Each class is then listed under the least fifth (one less ``similarity``) of
    its shingle hashes, under one of which every pair as alike as asked meets, whatever was edited; a 256-bit
    fingerprint over the shingles estimates their similarity.
    Lists are worked in blocks, so a large group of near copies is spread over tasks; a forest of its nearest
    links leaves each block first, then all links between classes still different. A link counts when the shingle sets
    of the whole texts prove it.
    """
    prints, _, classes = _near_duplicates(docs, similarity, shingle, True)
    alone = prints.groupBy("node").agg(F.min("doc_id").alias("first_id"))
    of = alone.join(classes.select("node", F.col("least.doc_id").alias("least_id")), "node", "left")
    return prints.select("doc_id", "node").join(of.select("node", F.coalesce("least_id", "first_id").alias("component_id")), "node").select("doc_id", "component_id")


def contiguous(batches, key: list[str]):
    """Runs of rows with equal keys from a sorted partition, as tables; a run may span batches."""
    held: list = []
    last = None
    for batch in batches:
        if not batch.num_rows:
            continue
        cols = [batch.column(batch.schema.get_field_index(k)).to_numpy(zero_copy_only=False) for k in key]
        change = np.zeros(batch.num_rows, dtype=bool)
        for c in cols:
            change[1:] |= c[1:] != c[:-1]
        cuts = np.concatenate([[0], np.nonzero(change)[0], [batch.num_rows]]).tolist()
        for a, b in zip(cuts[:-1], cuts[1:]):
            now = tuple(c[a] for c in cols)
            if last is not None and now != last:
                yield pa.Table.from_batches(held).combine_chunks()
                held = []
            last = now
            held.append(batch.slice(a, b - a))
    if held:
        yield pa.Table.from_batches(held).combine_chunks()


def drop_near_duplicates(docs: DataFrame, similarity: float = 0.8, shingle: int = 5) -> DataFrame:
    """One row of each class, that of the smallest known doc_id. Rows that share a doc_id but no class all stay."""
    _, one, classes = _near_duplicates(docs, similarity, shingle, False)
    # Written, so that its size is known to the join below: texts are shuffled only if it is large.
    lost = materialize(classes.where("first <> least").select("node"))
    kept = one.where("linked").join(lost, "node", "left_anti").select("doc")
    return one.where("not linked").select("doc").union(kept).select("doc.*")
