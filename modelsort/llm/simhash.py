"""SimHash near-duplicates, linked exactly through vantage-point trees.

Fingerprints are 64-bit SimHash over three-word shingles. Equal fingerprints
are one class first (a partial aggregate, so thousands of copies cost one row).
Classes are then dealt to shards by their Hamming distances to vantage points
over disjoint bit masks. Distances over disjoint masks add up, so the triangle
bounds of all masks share one radius: a class visits only shards whose shells
its radius overlaps. Within a shard, a vantage-point tree with one mask per
level answers all queries at once, level by level. No pair leaves a shard: each
shard contracts its links and returns at most one link per class and visit.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from modelsort.llm.bytetext import blocks, row_sums, utf8_view
from modelsort.llm.components import connected_components
from modelsort.llm.samples import free_name, quoted
from modelsort.plans.durable import materialize

SEED = 42
SHINGLE = 3
RADIUS = 3
#: Classes that a shard should hold at most on average.
SHARD_CLASSES = 20_000
_LANES = np.uint64(0x0101010101010101)


def _shingle_digests(text: bytes, size: int) -> list[bytes]:
    words = text.lower().split()
    digest = xxhash.xxh64_digest
    if len(words) <= size:
        return [digest(b" ".join(words), SEED)] if words else []
    line = b" ".join(words)
    lengths = np.fromiter(map(len, words), np.int64, len(words))
    starts = np.cumsum(lengths + 1) - lengths - 1
    ends = (starts + lengths)[size - 1 :].tolist()
    return [digest(line[a:b], SEED) for a, b in zip(starts.tolist(), ends, strict=False)]


def _majority(hashes: np.ndarray, bounds: np.ndarray) -> np.ndarray:
    """Bits set in over half of each row's hashes, counted in byte lanes of 64-bit words."""
    counts = np.diff(bounds)
    runs = -(-counts // 255)
    run_rows = np.concatenate([[0], np.cumsum(runs)])
    within = np.arange(run_rows[-1]) - np.repeat(run_rows[:-1], runs)
    run_starts = np.repeat(bounds[:-1], runs) + 255 * within
    out = np.zeros(len(counts), np.uint64)
    if not len(run_starts):
        return out
    for bit in range(8):
        lanes = np.add.reduceat((hashes >> np.uint64(bit)) & _LANES, run_starts)
        ones = row_sums(lanes.view(np.uint8).reshape(-1, 8).astype(np.int64), run_rows)
        for lane in range(8):
            out |= (2 * ones[:, lane] > counts).astype(np.uint64) << np.uint64(8 * lane + bit)
    return out


def fingerprint_array(texts: pa.Array, size: int = SHINGLE) -> np.ndarray:
    """SimHash of each text; null, empty and blank texts give zero."""
    data, offsets = utf8_view(texts)
    raw = data.tobytes()
    out = np.zeros(len(offsets) - 1, np.uint64)
    for a, b in blocks(offsets):
        rows = [_shingle_digests(raw[offsets[i] : offsets[i + 1]], size) for i in range(a, b)]
        bounds = np.concatenate([[0], np.cumsum([len(r) for r in rows])])
        hashes = np.frombuffer(b"".join(x for r in rows for x in r), ">u8").astype(np.uint64)
        out[a:b] = _majority(hashes, bounds)
    return out


def fingerprint(text: Column, size: int = SHINGLE) -> Column:
    """SimHash of a text column as a long (its bits, signed)."""

    def run(batches: Iterator[pa.Array]) -> Iterator[pa.Array]:
        for texts in batches:
            yield pa.array(fingerprint_array(texts, size).view(np.int64))

    run.__annotations__ = {"batches": Iterator[pa.Array], "return": Iterator[pa.Array]}
    return F.arrow_udf(run, "long").asNondeterministic()(text)


class VantageTree:
    """Vantage-point tree over distinct 64-bit fingerprints, built and searched level by level.

    Each node's vantage point is its first fingerprint; children are the shells
    of equal distance over the level's mask. A query keeps, per visited node,
    what is left of its radius after the shells passed so far.
    """

    def __init__(self, prints: np.ndarray, levels: int = 8):
        self.prints = np.asarray(prints, np.uint64)
        width = 64 // levels
        self.width = width
        self.masks = [np.uint64(((1 << width) - 1) << (width * i)) for i in range(levels)]
        order, node = np.arange(len(self.prints)), np.zeros(len(self.prints), np.int64)
        self.levels: list[tuple[np.ndarray, np.ndarray]] = []
        starts = np.zeros(min(1, len(order)), np.int64)
        for mask in self.masks:
            points = self.prints[order[starts]] & mask
            shell = np.bitwise_count((self.prints[order] & mask) ^ points[node]).astype(np.int64)
            key = node * (width + 1) + shell
            by_key = np.argsort(key, kind="stable")
            order, key = order[by_key], key[by_key]
            first = np.ones(len(key), bool)
            first[1:] = key[1:] != key[:-1]
            child = np.full(len(starts) * (width + 1), -1, np.int64)
            child[key[first]] = np.arange(first.sum())
            self.levels.append((points, child))
            node, starts = np.cumsum(first) - 1, np.flatnonzero(first)
        self.order, self.starts = order, np.append(starts, len(order))

    def within(self, queries: np.ndarray, radius: int) -> tuple[np.ndarray, np.ndarray]:
        """All (query index, print index) with a Hamming distance of ``radius`` or less."""
        parts = list(self.near(queries, radius)) or [(np.zeros(0, np.int64), np.zeros(0, np.int64))]
        return tuple(np.concatenate(x) for x in zip(*parts, strict=True))

    def near(self, queries: np.ndarray, radius: int, most: int = 1 << 21) -> Iterator[tuple[np.ndarray, np.ndarray]]:
        """The same in pieces of about ``most`` candidates, so that dense groups need no more memory."""
        q = np.arange(len(queries)) if len(self.prints) else np.zeros(0, np.int64)
        node, left = np.zeros(len(q), np.int64), np.full(len(q), radius)
        for mask, (points, child) in zip(self.masks, self.levels, strict=True):
            distance = np.bitwise_count((queries[q] & mask) ^ points[node]).astype(np.int64)
            parts = []
            for step in range(-radius, radius + 1):
                shell = distance + step
                ok = np.flatnonzero((left >= abs(step)) & (shell >= 0) & (shell <= self.width))
                to = child[node[ok] * (self.width + 1) + shell[ok]]
                ok, to = ok[to >= 0], to[to >= 0]
                parts.append((q[ok], to, left[ok] - abs(step)))
            q, node, left = (np.concatenate(x) for x in zip(*parts, strict=True))
        sizes = self.starts[node + 1] - self.starts[node]
        ends = np.cumsum(sizes)
        first = 0
        while first < len(q):
            last = max(first + 1, int(np.searchsorted(ends, (ends[first - 1] if first else 0) + most, side="right")))
            own = sizes[first:last]
            at = np.repeat(self.starts[node[first:last]] - (np.cumsum(own) - own), own) + np.arange(own.sum())
            who, x = np.repeat(q[first:last], own), self.order[at]
            near = np.bitwise_count(queries[who] ^ self.prints[x]) <= radius
            yield who[near], x[near]
            first = last


def _union(labels: np.ndarray, a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Least label of each connected set after adding links a-b."""
    while len(a):
        la, lb = labels[a], labels[b]
        open_ = la != lb
        if not open_.any():
            break
        a, b, la, lb = a[open_], b[open_], la[open_], lb[open_]
        np.minimum.at(labels, np.maximum(la, lb), np.minimum(la, lb))
        while not np.array_equal(labels, jumped := labels[labels]):
            labels = jumped
    return labels


def _link_shard(shard: pa.Table, radius: int, block: int = 4096) -> pa.Table:
    """Contracted links of one shard: those among its classes and with its visitors."""
    home = shard.column("home").to_numpy(zero_copy_only=False).astype(bool)
    nodes = shard.column("node").to_numpy()
    prints = shard.column("print").to_numpy().view(np.uint64)
    own = np.flatnonzero(home)
    labels = np.arange(len(nodes))
    if len(own):
        tree = VantageTree(prints[own])
        for start in range(0, len(prints), block):
            for q, x in tree.near(prints[start : start + block], radius):
                labels = _union(labels, q + start, own[x])
    moved = np.flatnonzero(labels != np.arange(len(labels)))
    return pa.table({"u": nodes[moved], "v": nodes[labels[moved]]}, schema=pa.schema([("u", pa.int64()), ("v", pa.int64())]))


def _shard_masks(count: int) -> list[int]:
    """Disjoint masks of the shard level: more of them for more classes, so that shards stay bounded."""
    parts = next((p for p, shards in ((2, 137), (4, 4_700)) if count <= shards * SHARD_CLASSES), 8)
    width = 64 // parts
    return [((1 << width) - 1) << (width * i) for i in range(parts)]


def _forward_steps(parts: int, radius: int) -> list[tuple[int, ...]]:
    """Shell offsets within the radius whose first non-zero is positive, and the zero offset."""
    steps: list[tuple[int, ...]] = [()]
    for _ in range(parts):
        steps = [(*s, d) for s in steps for d in range(-radius, radius + 1) if sum(map(abs, s)) + abs(d) <= radius]
    return [s for s in steps if s >= (0,) * parts]


def link_classes(classes: DataFrame, radius: int = RADIUS) -> DataFrame:
    """Contracted links ``u, v`` between classes ``print, node`` within ``radius`` bits.

    Distinct non-null prints and nodes are asked for. Every linked pair is
    connected by the rows returned; an empty input gives none.
    """
    count, vantage = classes.agg(F.count("*"), F.min_by("print", F.xxhash64("print"))).first()
    masks = _shard_masks(count)
    signed = [m - (1 << 64) if m >> 63 else m for m in masks]
    shells = [F.bit_count(F.col("print").bitwiseXOR(F.lit(vantage or 0)).bitwiseAND(F.lit(m))) for m in signed]
    cell = F.array(*shells)
    steps = F.array(*(F.array(*(F.lit(d) for d in s)) for s in _forward_steps(len(masks), radius)))
    visits = (
        classes.select("print", "node", cell.alias("cell"), F.explode(steps).alias("step"))
        .select("print", "node", F.zip_with("cell", "step", lambda c, d: c + d).alias("cell"), F.forall("step", lambda d: d == 0).alias("home"))
        .where(F.forall("cell", lambda c: c.between(0, 64 // len(masks))))
    )
    shard = visits.select(F.concat_ws(".", F.col("cell").cast("array<string>")).alias("shard"), "home", "print", "node")
    return shard.groupBy("shard").applyInArrow(lambda t: _link_shard(t, radius), "u long, v long")


def near_duplicates(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", radius: int = RADIUS, size: int = SHINGLE) -> DataFrame:
    """One row per document: ``doc_id, print, node, component_id``.

    ``node`` is the least id with the same fingerprint, ``component_id`` the
    least id reachable through links of ``radius`` bits or fewer. Null, empty
    and blank texts have fingerprint zero and are linked like any other. Ids
    must be whole numbers; documents without an id link others all the same, and
    get null where no document of their component has one. Repeated rows each
    keep a row. An empty table gives none. Other columns are not read.
    """
    prints = materialize(docs.select(F.col(id_col).cast("long").alias("doc_id"), fingerprint(F.col(text_col), size).alias("print")), "prints")
    classes = prints.groupBy("print").agg(F.min("doc_id").alias("node"))
    grouped = materialize(_grouped(classes, radius), "simhash-groups")
    least = grouped.groupBy("group").agg(F.min("node").alias("component_id"))
    resolved = grouped.join(least, "group").select("print", "node", "component_id")
    return prints.join(resolved, "print").select("doc_id", "print", "node", "component_id")


def _grouped(classes: DataFrame, radius: int) -> DataFrame:
    """Classes with their ``group``, the least fingerprint that links reach; a fingerprint is its own node, ids play no part."""
    linked = connected_components(link_classes(classes.select("print", F.col("print").alias("node")), radius), "simhash-links")
    return classes.join(linked.withColumnRenamed("node", "print"), "print", "left").withColumn("group", F.coalesce("component", "print")).drop("component")


def deduplicate(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", radius: int = RADIUS) -> DataFrame:
    """Documents with one kept per group: the one of least id, and of its repeats one.

    An id with texts of several fingerprints is a document for each of them, so a
    text that is near no other is never lost to one that shares its id. Null,
    empty and blank texts form one group. Documents without an id can't be told
    apart and all stay. Columns are unchanged, whatever their names; an empty
    table stays empty.
    """
    names = {n: free_name(docs, f"__{n}") for n in ("keep", "lead", "several", "print")}
    keep, lead, several, mark = names.values()
    own = docs.withColumn(keep, F.col(id_col).cast("long"))
    prints = materialize(own.where(F.col(keep).isNotNull()).select(F.col(keep).alias("doc_id"), fingerprint(F.col(text_col)).alias("print")), "prints")
    classes = prints.groupBy("print").agg(F.min("doc_id").alias("least"))
    leads = _grouped(classes, radius).groupBy("group").agg(F.min(F.struct("least", "print")).alias("lead")).select(F.col("lead")["least"].alias(keep), F.col("lead")["print"].alias(lead))
    texts = prints.groupBy(F.col("doc_id").alias(keep)).agg((F.min("print") != F.max("print")).alias(several))
    kept = own.join(leads.join(texts, keep), keep)
    # Only texts whose id has several fingerprints are read again.
    kept = kept.withColumn(mark, fingerprint(F.when(F.col(several), F.col(text_col)))).where(~F.col(several) | (F.col(mark) == F.col(lead)))
    repeats = keep_one(kept, keep, lead).select(*quoted(docs))
    return repeats.unionByName(own.where(F.col(keep).isNull()).select(*quoted(docs)))


def keep_one(df: DataFrame, *key: str) -> DataFrame:
    """One row of each non-null key (Spark combines before the shuffle)."""
    return df.dropDuplicates(list(key))
