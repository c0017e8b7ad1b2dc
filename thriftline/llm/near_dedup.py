"""Near-duplicate classes by MinHash signatures and a multi-index Hamming join.

A document's set holds its distinct shingles of ``shingle`` lower-cased words.  Its signature has ``SLOTS`` b-bit MinHash
slots; the distance of two signatures is the number of slots that differ.  The slots are split into ``CHUNKS`` chunks.  If at
most ``CHUNKS * (errors + 1) - 1`` slots differ, some chunk has at most ``errors`` differing slots (pigeonhole), so both
signatures agree there on all slots but ``errors``: every choice of slots left out of every chunk is one index key, and
two signatures under the distance threshold share a key for certain.  With 32 slots, 8 chunks and 1 error the threshold is 15
of 32; two sets at Jaccard 0.85 exceed it with probability below 4e-6, and still share a key in all but 3e-8 of such cases.

Nothing below emits the pairs of a bucket.  Equal sets are one class first.  Every bucket of a key names its smallest
class as pivot; each class goes, with its text, once to each of its pivots (about one).  Any two classes that share a key are members of
its pivot's group.  All full sets of a group are compared with the pivot's, which connects near copies in one row a member; those not
connected are compared with a few more centers, and only what is left meets the others, in blocks of bounded size, as far as the
distances to the pivot allow a link (Jaccard distance is a metric).  So no link is lost that would connect two components, and only
links that do leave a task.  Components come from repeated contraction to the smallest neighbour.  Sets are sets of 64-bit
hashes of shingles.  Keys that hold many rows are joined by ``skewed``.
"""

from __future__ import annotations

import hashlib
import itertools

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from thriftline.llm import rowkeys, skewed
from thriftline.llm import textscan as ts
from thriftline.llm.arrowrun import annotate, columns_of, give_back, pieces
from thriftline.shipping import durable, ship, written

SLOTS, CHUNKS, ERRORS, SLOT_BYTES = 32, 8, 1, 2
#: Members of a block under one pivot, and their shingles, about; a larger group is compared block against block.
BLOCK, BLOCK_SHINGLES = 256, 1 << 19
#: Further centers that the members of a group are compared with while more than a block of them is not connected.
ROUNDS = 4
#: So many groups (16 bytes each) may be sent to their rows; more meet them by key.
FEW_GROUPS = 1 << 19
_gen = np.random.Generator(np.random.PCG64(971))
_SCALE = _gen.integers(1, 1 << 63, SLOTS, dtype=np.uint64) * np.uint64(2) + np.uint64(1)
_SHIFT = _gen.integers(1, 1 << 63, SLOTS, dtype=np.uint64)


def shingle_sets(column: pa.Array, width: int) -> list[np.ndarray]:
    """The sorted distinct shingle hashes of each text; a text of fewer words has one shingle, without words none."""
    raw, offs, _ = ts.text_buffers(column)
    out: list[np.ndarray] = []
    for i, j in ts.blocks(offs):
        words = ts.Spans(raw, offs[i : j + 1], ts.NON_SPACE, ts.FOLD_ASCII)
        h = words.hashes()
        windows = ts.window_hashes(h, width)
        for a, b in zip(words.first[:-1].tolist(), words.first[1:].tolist(), strict=True):
            if b - a >= width:
                out.append(_distinct(windows[a : b - width + 1]))
            elif b > a:
                out.append(ts.window_hashes(h[a:b], b - a, seed=2 + b - a))
            else:
                out.append(np.zeros(0, np.uint64))
    return out


def _distinct(x: np.ndarray) -> np.ndarray:
    x = np.sort(x)
    return x[np.concatenate(([True], x[1:] != x[:-1]))]


def signatures(sets: list[np.ndarray]) -> np.ndarray:
    """The b-bit MinHash slots of each set, as rows of unsigned integers; rows of empty sets are zero."""
    out = np.zeros((len(sets), SLOTS), np.uint16)
    full = np.array([i for i, s in enumerate(sets) if len(s)], np.int64)
    at = 0
    while at < len(full):
        to, size = at, 0
        while to < len(full) and (to == at or size + len(sets[full[to]]) <= 1 << 17):
            size += len(sets[full[to]])
            to += 1
        part = [sets[i] for i in full[at:to]]
        flat = np.concatenate(part)
        starts = np.cumsum([0, *map(len, part[:-1])])
        with np.errstate(over="ignore"):
            for k in range(SLOTS):
                out[full[at:to], k] = (ts.mix(np.minimum.reduceat((flat ^ _SHIFT[k]) * _SCALE[k], starts)) & np.uint64(0xFFFF)).astype(np.uint16)
        at = to
    return out


def index_keys(slots: np.ndarray) -> np.ndarray:
    """All index keys of each signature: for each chunk, each choice of ``ERRORS`` slots left out."""
    width, keys = SLOTS // CHUNKS, []
    for c in range(CHUNKS):
        for left in itertools.combinations(range(width), ERRORS):
            with np.errstate(over="ignore"):
                key = np.full(len(slots), np.uint64(1 + len(keys)))
                for s in range(width):
                    if s not in left:
                        key = ts.mix(key * np.uint64(0x10001) + slots[:, c * width + s].astype(np.uint64))
            keys.append(key)
    return np.stack(keys, axis=1).view(np.int64)


def _described(shingle: int):
    def work(texts: pa.Array):
        sets = shingle_sets(texts, shingle)
        keys = index_keys(signatures(sets))
        full = np.array([len(s) > 0 for s in sets], bool)
        ids = [hashlib.blake2b(s.tobytes(), digest_size=16).digest() if len(s) else None for s in sets]
        offsets = np.concatenate(([0], np.cumsum(np.where(full, keys.shape[1], 0)))).astype(np.int32)
        lists = pa.ListArray.from_arrays(pa.array(offsets), pa.array(keys[full].ravel()))
        return [pa.array([len(s) for s in sets], pa.int64()), pa.array(ids, pa.binary()), lists]

    return work


def _links(percent: int, shingle: int):
    """Rows (pivot, bi, bj, block, id, text), ordered by the first three, to a forest of confirmed links (a, b)."""

    def forest(ids: np.ndarray, block: np.ndarray, sets: list[np.ndarray], same: bool) -> tuple[list, list]:
        n = len(ids)
        sizes = np.array([len(s) for s in sets], np.int64)
        flat = np.concatenate(sets)
        order = np.argsort(flat, kind="stable")
        ranked = flat[order]
        new = np.concatenate(([True], ranked[1:] != ranked[:-1]))
        code = np.empty(len(flat), np.int64)
        code[order] = np.cumsum(new) - 1
        shared = np.bincount(code) > 1
        column = np.cumsum(shared) - 1
        row = np.repeat(np.arange(n), sizes)
        use = shared[code]
        row, col = row[use], column[code[use]]
        common = np.zeros((n, n), np.float32)
        order = np.argsort(col, kind="stable")
        row, col = row[order], col[order]
        width = max(256, (1 << 22) // n)
        for start in range(0, int(col[-1]) + 1 if len(col) else 0, width):
            a, b = np.searchsorted(col, (start, start + width))
            part = np.zeros((n, width), np.float32)
            part[row[a:b], col[a:b] - start] = 1
            common += part @ part.T
        inter = common.astype(np.int64)
        union = sizes[:, None] + sizes[None, :] - inter
        linked = np.triu(100 * inter >= percent * union, 1)
        if not same:
            linked &= block[:, None] != block[None, :]
        left, right = np.nonzero(linked)
        parent = list(range(n))

        def find(x):
            while parent[x] != x:
                parent[x] = parent[parent[x]]
                x = parent[x]
            return x

        for x, y in zip(left.tolist(), right.tolist(), strict=True):
            x, y = find(x), find(y)
            if x != y:
                if ids[x] > ids[y]:
                    x, y = y, x
                parent[y] = x
        roots = [find(x) for x in range(n)]
        moved = [x for x in range(n) if roots[x] != x]
        return [int(ids[roots[x]]) for x in moved], [int(ids[x]) for x in moved]

    def run(batches):
        held: list[pa.RecordBatch] = []
        key = None

        def flush():
            if not held:
                return None
            group = pa.Table.from_batches(held)
            if group.num_rows < 2:
                return None
            sets = shingle_sets(group.column("text").combine_chunks(), shingle)
            ids, block = group.column("id").to_numpy(), group.column("block").to_numpy()
            a, b = forest(ids, block, sets, key[1] == key[2])
            return pa.RecordBatch.from_arrays([pa.array(a, pa.int64()), pa.array(b, pa.int64())], names=["a", "b"]) if a else None

        for batch in batches:
            if not batch.num_rows:
                continue
            cols = [batch.column(i).to_numpy() for i in range(3)]
            change = np.zeros(batch.num_rows, bool)
            for c in cols:
                change[1:] |= c[1:] != c[:-1]
            starts = [0, *np.flatnonzero(change).tolist(), batch.num_rows]
            for s, e in zip(starts[:-1], starts[1:], strict=True):
                now = tuple(int(c[s]) for c in cols)
                if now != key:
                    done = flush()
                    if done is not None:
                        yield done
                    held, key = [], now
                held.append(batch.slice(s, e - s))
        done = flush()
        if done is not None:
            yield done
        held.clear()
        give_back()

    return run


def _stars(percent: int, shingle: int):
    """Rows (grp, salt, role, id, text), ordered by the first three, one center (role 0) before its members, to each member's ring and link.

    A ring is a distance to the center of a multiple of what a link may have at most, so that linked sets are in one ring or in neighbours.
    """

    def run(batches):
        key, center, name = None, None, None
        for batch in batches:
            for piece in pieces(batch, 4, 4 << 20):
                grp, salt, _, ids = (piece.column(i).to_numpy() for i in range(4))
                sets = shingle_sets(piece.column(4), shingle)
                cuts = [0, *(np.flatnonzero((grp[1:] != grp[:-1]) | (salt[1:] != salt[:-1])) + 1).tolist(), len(grp)]
                out = []
                for a, b in zip(cuts[:-1], cuts[1:], strict=True):
                    if a == b:
                        continue
                    if key != (grp[a], salt[a]):
                        key, center, name = (grp[a], salt[a]), sets[a], ids[a]
                        a += 1
                    if a == b:
                        continue
                    sizes = np.array([len(s) for s in sets[a:b]], np.int64)
                    flat = np.concatenate(sets[a:b])
                    same = center[np.minimum(np.searchsorted(center, flat), len(center) - 1)] == flat
                    inter = np.add.reduceat(same, np.cumsum(sizes) - sizes, dtype=np.int64)
                    union = sizes + len(center) - inter
                    ring = 100 * (union - inter) // np.maximum(union * (100 - percent), 1)
                    out.append((np.full(b - a, key[0]), np.full(b - a, name), ids[a:b], sizes, ring, 100 * inter >= percent * union))
                if out:
                    columns = [pa.array(np.concatenate(c)) for c in zip(*out, strict=True)]
                    yield pa.RecordBatch.from_arrays(columns, names=["grp", "center", "id", "size", "ring", "linked"])
        give_back()

    return run


def _tasks(df: DataFrame) -> int:
    spark = df.sparkSession
    return max(int(spark.conf.get("spark.sql.shuffle.partitions")), spark.sparkContext.defaultParallelism)


def _compared(rows: DataFrame, counts: DataFrame, total: int, percent: int, shingle: int) -> DataFrame:
    """Each of the rows (grp, center, id, text) with the center of its group: one row a member, a large group (grp, n) being split over tasks."""
    bound = skewed.hot_bound(total)
    large = counts.where(F.col("n") > bound).select("grp", F.ceil(F.col("n") / F.lit(bound)).cast("int").alias("parts"))
    split = rows.join(F.broadcast(large), "grp", "left").withColumn("parts", F.coalesce("parts", F.lit(1)))
    head = F.col("id") == F.col("center")
    salts = F.when(head, F.sequence(F.lit(0), F.col("parts") - 1)).otherwise(F.array(F.pmod(F.xxhash64("id"), F.col("parts")).cast("int")))
    sent = split.select("grp", F.explode(salts).alias("salt"), F.when(head, 0).otherwise(1).alias("role"), "id", "text")
    dealt = sent.repartition(_tasks(rows), "grp", "salt").sortWithinPartitions("grp", "salt", "role")
    return durable(dealt.mapInArrow(_stars(percent, shingle), "grp long, center long, id long, size long, ring long, linked boolean"))


def _of_groups(rows: DataFrame, groups: DataFrame) -> DataFrame:
    """The rows of these groups (grp, ...), which are sent to the rows if they are few enough."""
    return rows.join(F.broadcast(groups) if groups.count() <= FEW_GROUPS else groups, "grp")


def _rest(state: DataFrame, rows: DataFrame, total: int, percent: int, shingle: int) -> DataFrame:
    """Links (a, b) among the members (grp, id, size, ring, main) that are not known to hang together, and between them and the others.

    Blocks of members (texts in ``rows``) meet pair by pair; those of the main component do not meet each other, nor do rings that are no neighbours.
    """
    sizes = state.groupBy("grp", "main", "ring").agg(F.count("*").alias("n"), F.sum("size").alias("size"))
    blocks = F.greatest(F.ceil(F.col("n") / F.lit(BLOCK)), F.ceil(F.col("size") / F.lit(BLOCK_SHINGLES))).cast("long")
    cell = F.struct("main", "ring", "n", blocks.alias("blocks"))
    groups = sizes.groupBy("grp").agg(F.sum("n").alias("weight"), F.collect_list(cell).alias("cells"), F.min("main").alias("done")).where("not done").drop("done")
    placed = skewed.joined(state, groups, ["grp"], "weight", total)
    own = F.filter("cells", lambda c: (c["main"] == F.col("main")) & (c["ring"] == F.col("ring")))[0]

    def code(main, ring, block):
        return F.when(main, F.lit(1 << 56)).otherwise(F.lit(0)) + ring * (1 << 32) + block

    near = F.filter("cells", lambda c: (F.abs(c["ring"] - F.col("ring")) <= 1) & ~(c["main"] & F.col("main")))
    others = F.flatten(F.transform(near, lambda c: F.transform(F.sequence(F.lit(0).cast("long"), c["blocks"] - 1), lambda i: code(c["main"], c["ring"], i))))
    alone = (own["n"] == 1) & ~F.col("main")
    placed = placed.withColumn("block", code(F.col("main"), F.col("ring"), F.pmod(F.xxhash64("id"), own["blocks"]))).withColumn("alone", alone)
    met = placed.withColumn("other", F.explode(others)).where(~(F.col("alone") & (F.col("other") == F.col("block"))))
    met = durable(met.select("grp", F.least("block", "other").alias("bi"), F.greatest("block", "other").alias("bj"), "block", "id"))
    texts = _of_groups(rows.select("grp", "id", "text"), met.select("grp").distinct())
    sent = met.join(texts, ["grp", "id"]).select("grp", "bi", "bj", "block", "id", "text")
    dealt = sent.repartition(_tasks(state), "grp", "bi", "bj").sortWithinPartitions("grp", "bi", "bj")
    return dealt.mapInArrow(_links(percent, shingle), "a long, b long")


def links_of(members: DataFrame, texts: DataFrame, percent: int, shingle: int) -> DataFrame:
    """Links (a, b) that connect all members (grp, id) of a group that full sets connect; ``grp`` is the id of one of them.

    Every member is compared with the first of its group, in one row.  Where many are not linked to it, they are compared with further centers,
    up to ``ROUNDS`` times; what meets the main component in this way is done.  The few others are compared with all that may be linked to them.
    """
    groups = members.groupBy("grp").agg(F.count("*").alias("n"))
    total = members.count()
    heads = groups.select("grp", F.col("grp").alias("id"))
    # The only move of all texts: members and first centers get theirs.
    rows = written(members.select("grp", "id").unionAll(heads).join(texts, "id").select("grp", "id", "text"))
    found = _compared(rows.withColumn("center", F.col("grp")), groups, total, percent, shingle)
    out = found.where("linked").select(F.col("center").alias("a"), F.col("id").alias("b"))
    state = found.select("grp", "id", "size", "ring", F.col("linked").alias("main"))
    rows = rows.where("id <> grp")
    for turn in range(ROUNDS):
        each = state.groupBy("grp").agg(F.count("*").alias("n"), F.count_if(~F.col("main")).alias("open"), F.min(F.when(~F.col("main"), F.struct(F.xxhash64("id", F.lit(turn)), F.col("id"))))["id"].alias("center"))
        centers = each.where(F.col("open") > BLOCK).select("grp", "center", "n")
        if centers.isEmpty():
            break
        centers = durable(centers)
        found = _compared(_of_groups(rows, centers.select("grp", "center")), centers, total, percent, shingle).where("linked").select("grp", "center", "id")
        out = out.unionAll(found.select(F.col("center").alias("a"), F.col("id").alias("b")))
        known = found.join(state.select("grp", "id", "main"), ["grp", "id"])
        merged = known.groupBy("grp", "center").agg(F.max("main").alias("met"), F.count("*").alias("weight")).where("met").drop("met")
        more = skewed.joined(found, merged, ["grp", "center"], "weight", total).select("grp", "id")
        more = more.unionAll(merged.select("grp", F.col("center").alias("id"))).withColumn("now", F.lit(True))
        state = durable(state.join(more, ["grp", "id"], "left").withColumn("main", F.col("main") | F.coalesce("now", F.lit(False))).drop("now"))
    return out.unionAll(_rest(state, rows, total, percent, shingle))


def smallest_reachable(links: DataFrame) -> DataFrame:
    """(node, component) for every node of the links (a, b), component being the smallest node reachable.

    Each round ties every node and its neighbours to the smallest of them; the links become stars.  Each round is cut with
    a checkpoint, and only a count and a checksum come to the driver.
    """
    edges = links.select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v")).where("u <> v").distinct()
    edges = durable(edges)
    before = None
    while True:
        mark = edges.agg(F.count("*").alias("n"), F.bit_xor(F.xxhash64("u", "v")).alias("x")).first()
        if before == mark or not mark["n"]:
            return edges.select(F.col("u").alias("node"), F.col("v").alias("component"))
        before = mark
        both = edges.unionAll(edges.select(F.col("v").alias("u"), F.col("u").alias("v")))
        low = both.groupBy("u").agg(F.least(F.min("v"), F.first("u")).alias("m"), F.count("*").alias("weight"))
        tied = skewed.joined(both, low, ["u"], "weight", 2 * mark["n"]).select(F.explode(F.array(F.struct(F.col("v").alias("u"), F.col("m").alias("v")), F.struct("u", F.col("m").alias("v")))).alias("e"))
        edges = durable(tied.select("e.u", "e.v").where("u <> v").distinct())


def grouped(told: rowkeys.Told, key: str, shingle: int, percent: int) -> DataFrame:
    """(key, doc_id, n_shingles, component) for each row, ``component`` being the smallest key linked; null for rows without key."""
    spark = told.docs.sparkSession
    ship(spark)
    docs = told.docs.select(F.col(key).alias("key"), "doc_id", "text")
    rows = written(annotate(docs, lambda: _described(shingle), [("n_shingles", "long"), ("set_id", "binary"), ("keys", "array<bigint>")], keep_text=False))
    keyed = rows.where("key is not null and set_id is not null")
    classes = written(keyed.groupBy("set_id").agg(F.min("key").alias("id"), F.min_by("keys", "key").alias("keys"), F.count("*").alias("n_rows")))
    sizes = classes.agg(F.count("*").alias("classes"), F.sum("n_rows").alias("rows")).first()
    index = classes.select("id", F.explode("keys").alias("k"))
    shared = index.groupBy("k").agg(F.min("id").alias("grp"), F.count("*").alias("weight")).where("weight > 1")
    members = skewed.joined(index, shared, ["k"], "weight", sizes["classes"] * len(index_keys(np.zeros((1, SLOTS), np.uint16))[0])).where("id <> grp").select("grp", "id").distinct()
    # One row stands for a class: that of its smallest key.
    texts = docs.where("key is not null").select(F.col("key").alias("id"), "text")
    if told.repeated:
        texts = texts.join(classes.select("id"), "id", "left_semi").dropDuplicates(["id"])
    found = smallest_reachable(links_of(durable(members), texts, percent, shingle))
    named = classes.join(found.withColumnRenamed("node", "id"), "id", "left").select("set_id", F.coalesce("component", "id").alias("component"), "n_rows")
    own = rows.select("key", "doc_id", "n_shingles", F.when(F.col("key").isNotNull(), F.col("set_id")).alias("set_id"))
    out = skewed.joined(own, named, ["set_id"], "n_rows", sizes["rows"] or 0, outer=True)
    return out.select("key", "doc_id", "n_shingles", F.coalesce("component", "key").alias("component"))


def near_duplicates(docs: DataFrame, shingle: int = 3, percent: int = 85) -> DataFrame:
    """doc_id, n_shingles, component_id and kept for each row of ``docs`` (doc_id, text).

    Two documents are linked if 100 * |A and B| >= percent * |A or B| for their shingle sets.  Null texts and texts without words
    have an empty set and no link; they are their own component.  Repeated rows are equal sets, so linked, and kept alike.  Rows of one
    doc_id and different texts are different documents: component_id is the smallest doc_id each reaches, and of such rows that are linked with each
    other only one is kept.  A row without a doc_id is linked with nothing: component_id is null and kept is true.  Ties do not arise: the
    smallest doc_id names a component.  No rows in, no rows out.
    """
    told = rowkeys.told_apart(columns_of(docs, "doc_id", "text"), "row_key")
    out = grouped(told, "row_key", shingle, percent)
    kept = F.coalesce(F.col("key") == F.col("component"), F.lit(True))
    if not told.renumbered:
        return out.select("doc_id", "n_shingles", F.col("component").cast(docs.schema["doc_id"].dataType).alias("component_id"), kept.alias("kept"))
    out = written(out)
    names = out.groupBy("component").agg(F.count("*").alias("weight")).where("component is not null")
    names = names.join(out.where("key = component").groupBy("key").agg(F.min("doc_id").alias("component_id")), F.col("key") == F.col("component")).drop("key")
    return skewed.joined(out, names, ["component"], "weight", out.count(), outer=True).select("doc_id", "n_shingles", "component_id", kept.alias("kept"))
