"""Exact n-gram Jaccard join by signature trees.

Word shingle sets are compared at a threshold given in percent; equal sets are one node.

1. Who can link.  A set that links loses at most ``n - ceil(t n)`` of its shingles to its partner.
   The shingles of one part of the hash space are dealt by hash, and a set of which more than that
   many occur nowhere else links with nothing and is done.  The part is as large as the threshold
   needs for the rule to bite; no set that links is ever left out.
2. Clusters.  Two sets that link differ in at most D shingles, so of D+1 hash parts (plus spare
   parts for empty ones) at least one non-empty part is equal in both.  Each task and each bucket of
   such part signatures keeps a spanning forest of the sets that share one, at most one edge for a
   set; the forests' components are the candidate clusters.
3. Signature trees.  Inside a cluster a node holds the OR of its members' token bitmaps and the
   range of their sizes.  A dual traversal drops node pairs whose largest possible overlap is too
   small; surviving leaf pairs are verified on the sets.  A cluster of more than ``block`` sets is
   cut into blocks that are leaves of a tree of rows: its levels are traversed by joins of node
   pairs, and only the sets of surviving pairs of blocks travel.  Sets linked to the cluster's leader
   are connected already, so a pair of blocks needs at least one set that is not.

Defined results: null or blank text has an empty set, n_shingles 0 and links with nothing;
equal sets link; a null id keeps its row with a null component; repeated rows keep their rows, and
rows that share an id are judged each by its own text; further columns are ignored; an empty table
gives an empty table.
"""

from __future__ import annotations

import math
import pickle

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from gradsift.llm import kernels as K
from gradsift.llm.common import BROADCAST_ROWS, connected_components, discard, materialise, maybe_broadcast, table
from gradsift.llm.suffix_dedup import _cut, _deal, _grow, _steps, _thin, _wide

#: Most sets that one tree inside a task holds, and bytes of them.
BLOCK, BLOCK_BYTES = 256, 4 << 20
FANOUT = 8
#: Bits of the bitmap of a block.
BLOCK_BITS = 1 << 16
#: Parts into which the rows of one key are dealt where a key may be very frequent.
SALTS = 32
#: Leaders of large clusters, and bytes of one's set, up to which they are broadcast (64 MB in all).
LEADERS, LEADER_BYTES = 200, 320_000
#: Bytes of text, or of sets, for each bucket.
BUCKET_BYTES = 8 << 20


class Bands:
    """Size bands: a set links only with sets of its own band or of a neighbour."""

    def __init__(self, percent: int):
        if not 50 <= percent <= 100:
            raise ValueError("threshold in percent, 50 to 100")
        self.percent, self.low = percent, [1, 2]
        self.parts: dict[int, tuple[int, int]] = {}

    def band(self, n: int) -> int:
        while self.low[-1] <= n:
            self.low.append(max(self.low[-1] + 1, (self.low[-1] - 1) * 100 // self.percent + 1))
        return int(np.searchsorted(self.low, n, side="right")) - 1

    def shape(self, level: int) -> tuple[int, int]:
        """(parts, spare parts) of a level, which holds its own band and the next."""
        if level not in self.parts:
            while len(self.low) < level + 3:
                self.band(self.low[-1])
            top = self.low[level + 1] - 1
            differ = (top + min(self.low[level + 2] - 1, top * 100 // self.percent)) * (100 - self.percent) // (100 + self.percent)
            spare = 0
            if differ:
                m = differ + 2
                mean = m * math.exp(-self.low[level] / m)
                spare = math.ceil(1 + mean + 6 * math.sqrt(mean))
            self.parts[level] = differ + 1 + spare, spare
        return self.parts[level]


def part_keys(s: np.ndarray, bands: Bands) -> np.ndarray:
    """Signatures of a sorted set: one per non-empty part, at its own level and the one below."""
    level, out = bands.band(len(s)), []
    code = K.mix(s + K.U(0x51ED270B))
    for lv in (level, level - 1) if level else (level,):
        m, spare = bands.shape(lv)
        part = (s % K.U(m)).astype(np.int64)
        order = np.argsort(part, kind="stable")
        p = part[order]
        first = np.flatnonzero(np.r_[True, p[1:] != p[:-1]])
        own = K.mix(np.add.reduceat(code[order], first) + (p[first] + (lv << 32)).astype(np.uint64) * K.STEP[9])
        out.append(own)
        if m - len(first) > spare:  # too many empty parts to rely on the others
            none = np.setdiff1d(np.arange(m), p[first]).astype(np.uint64)
            out.append(K.mix((none + K.U(lv << 32)) * K.STEP[10] + K.U(7)))
    return np.concatenate(out)


def digest(s: np.ndarray) -> tuple[int, int]:
    """Two signed 64-bit digests of a set, equal for equal sets; the first is the name of its node."""
    d = np.array([K.mix(s).sum(dtype=np.uint64), (K.mix(s ^ K.STEP[11]) * K.STEP[12]).sum(dtype=np.uint64)], np.uint64)
    a, b = d.view(np.int64).tolist()
    return a, b


# 1. who can link ----------------------------------------------------------------

#: kind 0: row a of its piece (b: set size, c and d: digest, need: shared shingles it must have);
#: kind 1: shingles of bucket a, packed by row; a piece is some MB of one task's texts.
TOLD = "kind int, piece long, a long, doc_id long, b long, c long, d long, need long, blob binary"


def part_of_space(percent: int) -> int:
    """The rule looks at one shingle in so many; 60 % of those must still be shared by a set that links."""
    return max(1, min(64, 40 // (100 - percent))) if percent < 100 else 64


def _tell(words: int, percent: int, buckets: int, every: int):
    def run(batches):
        task, count = TaskContext.get().partitionId(), 0
        for batch in batches:
            data, offsets = K.raw(batch.column(1))
            null = batch.column(0).is_null().to_numpy(zero_copy_only=False)
            for i, j in K.pieces(offsets, BUCKET_BYTES):
                yield tell((task << 32) + count, batch.column(0).slice(i, j - i), null[i:j], data, offsets[i : j + 1])
                count += 1

    def tell(piece, column, null, data, offsets):
        rows, owner, token, seen = [], [], [], set()
        for i, j in K.pieces(offsets):
            lo, hi = offsets[i], offsets[j]
            h, first = K.words(data[lo:hi], offsets[i : j + 1] - lo)
            for k, s in enumerate(K.shingles(h, first, words), i):
                c, d = digest(s)
                some = s[(s >> K.U(58)) % K.U(every) == 0] if every > 1 else s
                rows.append((len(s), c, d, len(some) - (len(s) - -(-percent * len(s) // 100))))
                if len(some) and not null[k] and (c, d) not in seen:  # equal sets of a piece speak once
                    seen.add((c, d))
                    owner.append(np.full(len(some), k, np.int64))
                    token.append(some)
        n = len(rows)
        own = np.concatenate(owner) if owner else np.zeros(0, np.int64)
        key = K.mix(np.concatenate(token)) if token else np.zeros(0, np.uint64)
        dealt = [(b, pickle.dumps([_cut(key[part] >> K.U(32), 4), _thin(_steps(own[part]), 4)], 5)) for b, part in _deal(key, buckets)]
        m = len(dealt)
        size, c, d, need = (np.array(x, np.int64) for x in zip(*rows, strict=True)) if rows else (np.zeros(0, np.int64),) * 4
        pad = lambda x: pa.concat_arrays([pa.array(x, pa.int64()), pa.nulls(m, pa.int64())])
        return pa.RecordBatch.from_arrays(
            [
                pa.array(np.r_[np.zeros(n, np.int32), np.ones(m, np.int32)]), pa.array(np.full(n + m, piece, np.int64)), pa.array([*range(n), *(b for b, _ in dealt)], pa.int64()),
                pa.concat_arrays([column.cast(pa.int64()), pa.nulls(m, pa.int64())]), pad(size), pad(c), pad(d), pad(need), pa.concat_arrays([pa.nulls(n, pa.binary()), pa.array([x for _, x in dealt], pa.binary())]),
            ],
            [x.split()[0] for x in TOLD.split(", ")],
        )

    return run


def _shared_of_bucket(t: pa.Table) -> pa.Table:
    """Per row of a piece the number of its shingles in this bucket that another row has too."""
    parts = [pickle.loads(x) for x in t.column("blob").to_pylist()]
    key = np.concatenate([_grow(k, 4) for k, _ in parts])
    own = [np.cumsum(_wide(o, 4).astype(np.int64)) for _, o in parts]
    order = np.argsort(key, kind="stable")
    same = key[order][1:] == key[order][:-1]
    shared = np.zeros(len(key), bool)
    shared[order] = np.r_[False, same] | np.r_[same, False]
    edge = np.cumsum([0, *(len(o) for o in own)])
    pieces, rows, counts = [], [], []
    for p, o, a, b in zip(t.column("piece").to_pylist(), own, edge, edge[1:], strict=False):
        row, n = np.unique(o[shared[a:b]], return_counts=True)
        if len(row):
            pieces.append(p)
            rows.append(_thin(_steps(row), 4))
            counts.append(_thin(n.astype(np.uint64), 4))
    return pa.table({"piece": pa.array(pieces, pa.int64()), "row": pa.array(rows, pa.binary()), "n": pa.array(counts, pa.binary())})


def _shared_of_piece(t: pa.Table) -> pa.Table:
    row = np.concatenate([np.cumsum(_wide(x, 4).astype(np.int64)) for x in t.column("row").to_pylist()])
    n = np.concatenate([_wide(x, 4).astype(np.int64) for x in t.column("n").to_pylist()])
    total = np.bincount(row, n).astype(np.int64)
    at = np.flatnonzero(total)
    piece = t.column("piece")[0].as_py()
    return pa.table({"piece": pa.array([piece] * len(at), pa.int64()), "a": pa.array(at, pa.int64()), "shared": pa.array(total[at], pa.int64())})


# 2. clusters ----------------------------------------------------------------------


def forest(key: np.ndarray, node: np.ndarray):
    """Rows kept (the first holder of each key), and a spanning forest of the nodes that share keys.

    The forest has one edge (node, root) for each node that is no root, with its number of shared keys.
    """
    order = np.lexsort((node, key))
    fresh = np.ones(len(order), bool)
    fresh[1:] = key[order][1:] != key[order][:-1]
    head = order[np.maximum.accumulate(np.where(fresh, np.arange(len(order)), 0))] if len(order) else order
    other = node[order] != node[head]
    u, v = node[order][other], node[head][other]
    names, at = np.unique(np.r_[u, v], return_inverse=True)
    a, b = at[: len(u)], at[len(u) :]
    root = np.arange(len(names))
    while True:  # each round hangs roots on the smallest neighbouring root, then flattens
        x, y = root[a], root[b]
        open_ = x != y
        if not open_.any():
            break
        low = np.minimum(x, y)[open_]
        np.minimum.at(root, x[open_], low)
        np.minimum.at(root, y[open_], low)
        while (root[root] != root).any():
            root = root[root]
    times = np.bincount(a, minlength=len(names)) + np.bincount(b, minlength=len(names))
    hung = np.flatnonzero(root != np.arange(len(names)))
    return order[fresh], names[hung], names[root[hung]], times[hung]


#: kind 1: a forest's edge (node, a) with n shared signatures; kind 2: signatures of bucket a, packed.
SIGNED = "kind int, node long, a long, n long, blob binary"


def _signed(node, a, n, kind: int, blobs=None) -> pa.RecordBatch:
    col = lambda x: pa.nulls(len(a), pa.int64()) if x is None else pa.array(x, pa.int64())
    return pa.RecordBatch.from_arrays(
        [pa.array(np.full(len(a), kind, np.int32)), col(node), col(a), col(n), pa.nulls(len(a), pa.binary()) if blobs is None else pa.array(blobs, pa.binary())],
        [x.split()[0] for x in SIGNED.split(", ")],
    )


def _signatures(percent: int, buckets: int):
    def run(batches):
        bands = Bands(percent)
        for batch in batches:
            node, sets = batch.column("node").to_numpy(), _unpack(batch.column("shingles"))
            size = np.cumsum([0, *(8 * len(s) for s in sets)])
            for i, j in K.pieces(size, BUCKET_BYTES):
                keys = [part_keys(s, bands) for s in sets[i:j]]
                key = np.concatenate(keys) if keys else np.zeros(0, np.uint64)
                own = np.repeat(node[i:j], [len(k) for k in keys])
                kept, u, v, n = forest(key, own)  # equal signatures of a piece travel once
                yield _signed(u, v, n, 1)
                kept = kept[np.argsort(own[kept], kind="stable")]
                key, own = key[kept], own[kept]
                dealt = [(b, pickle.dumps([_cut(key[part] >> K.U(16), 6), _thin(_steps(own[part]), 8)], 5)) for b, part in _deal(key, buckets)]
                yield _signed(None, [b for b, _ in dealt], None, 2, [x for _, x in dealt])

    return run


def _forest_of_bucket(t: pa.Table) -> pa.Table:
    parts = [pickle.loads(x) for x in t.column("blob").to_pylist()]
    key = np.concatenate([_grow(k, 6) for k, _ in parts])
    node = np.concatenate([np.cumsum(_wide(d, 8).view(np.int64)) for _, d in parts])
    _, u, v, n = forest(key, node)
    return pa.table({"node": pa.array(u, pa.int64()), "a": pa.array(v, pa.int64()), "n": pa.array(n, pa.int64())})


def _sets(words: int):
    """(node, n, shingles) of the texts whose set is the wanted one."""

    def run(batches):
        for batch in batches:
            data, offsets = K.raw(batch.column("text"))
            want, node, n, out = batch.column("node").to_pylist(), [], [], []
            for i, j in K.pieces(offsets):
                lo, hi = offsets[i], offsets[j]
                h, first = K.words(data[lo:hi], offsets[i : j + 1] - lo)
                for k, s in enumerate(K.shingles(h, first, words), i):
                    if len(s) and digest(s)[0] == want[k]:
                        node.append(want[k])
                        n.append(len(s))
                        out.append(s.tobytes())
            yield pa.RecordBatch.from_arrays([pa.array(node, pa.int64()), pa.array(n, pa.int64()), pa.array(out, pa.binary())], ["node", "n", "shingles"])

    return run


# 3. signature trees -----------------------------------------------------------------


def linked(a: np.ndarray, b: np.ndarray, percent: int) -> bool:
    small, large = (a, b) if len(a) <= len(b) else (b, a)
    if 100 * len(small) < percent * len(large):
        return False
    at = np.searchsorted(large, small)
    both = int((large[np.minimum(at, len(large) - 1)] == small).sum())
    return 100 * both >= percent * (len(a) + len(b) - both)


def bitmaps(sets: list[np.ndarray], bits: int) -> np.ndarray:
    maps = np.zeros((len(sets), bits // 64), np.uint64)
    for row, s in zip(maps, sets, strict=True):
        at = (s >> K.U(7)) % K.U(bits)
        np.bitwise_or.at(row, (at >> K.U(6)).astype(np.int64), K.U(1) << (at & K.U(63)))
    return maps


class SignatureTree:
    """Leaves in the order given; each level ORs the bitmaps of up to FANOUT nodes below.

    A level is (bitmaps, smallest sizes, largest sizes, most shingles that share a bit with another).
    """

    def __init__(self, sets: list[np.ndarray], bits: int, height: int = 0):
        size = np.array([len(s) for s in sets], np.int64)
        maps = bitmaps(sets, bits)
        spare = size - np.bitwise_count(maps).sum(1, dtype=np.int64)
        self.levels = [(maps, size, size, spare)]
        while len(self.levels[-1][0]) > 1 or len(self.levels) < height:
            maps, low, high, spare = self.levels[-1]
            at = np.arange(0, len(maps), FANOUT)
            self.levels.append((np.bitwise_or.reduceat(maps, at, axis=0), np.minimum.reduceat(low, at), np.maximum.reduceat(high, at), np.maximum.reduceat(spare, at)))


def _survive(a, b, i, j, percent):
    """Which node pairs may hold a link, and the bound of their overlap."""
    (m1, l1, h1, s1), (m2, l2, h2, s2) = a, b
    keep = (100 * h1[i] >= percent * l2[j]) & (100 * h2[j] >= percent * l1[i])
    i, j = i[keep], j[keep]
    bound = np.zeros(len(i), np.int64)
    for c in range(0, len(i), 4096):
        x, y = i[c : c + 4096], j[c : c + 4096]
        bound[c : c + 4096] = np.bitwise_count(m1[x] & m2[y]).sum(1, dtype=np.int64)
    bound = np.minimum(bound + np.minimum(s1[i], s2[j]), np.minimum(h1[i], h2[j]))
    keep = bound * (100 + percent) >= percent * (l1[i] + l2[j])
    return i[keep], j[keep], bound[keep]


def _descend(one: SignatureTree, two: SignatureTree, percent: int):
    """Pairs of leaves that may link, by dual traversal; of one tree with itself each pair once."""
    i = j = np.zeros(1, np.int64)
    for level in range(len(one.levels) - 1, -1, -1):
        i, j, bound = _survive(one.levels[level], two.levels[level], i, j, percent)
        if level and len(i):
            step = np.arange(FANOUT)
            left = np.repeat(i[:, None] * FANOUT + step, FANOUT, axis=1)
            right = np.tile(j[:, None] * FANOUT + step, (1, FANOUT))
            keep = (left < len(one.levels[level - 1][0])) & (right < len(two.levels[level - 1][0]))
            if one is two:
                keep &= left <= right
            i, j = left[keep], right[keep]
    return i, j, bound


def tree_links(sets: list[np.ndarray], percent: int, other: list[np.ndarray] | None = None) -> list[tuple[int, int]]:
    """Links that connect what the threshold connects; pairs connected already are skipped.

    Within ``sets``, or between ``sets`` and ``other`` (whose members count on behind them).
    """
    if not sets or (other is None and len(sets) < 2) or (other is not None and not other):
        return []
    own, top = np.array(sorted(range(len(sets)), key=lambda x: len(sets[x]))), max(map(len, sets))
    two = own if other is None else np.array(sorted(range(len(other)), key=lambda x: len(other[x])))
    top = max(top, max(map(len, other or sets)))
    bits = min(max(64, 1 << (2 * max(1, top) - 1).bit_length()), 1 << 16)
    height = 1 + math.ceil(math.log(max(len(own), len(two)), FANOUT) + 1e-9) if other is not None else 0
    x = SignatureTree([sets[k] for k in own], bits, height)
    y = x if other is None else SignatureTree([other[k] for k in two], bits, len(x.levels))
    while len(x.levels) < len(y.levels):
        x.levels.append(x.levels[-1])
    i, j, bound = _descend(x, y, percent)
    if other is None:
        keep = i < j
        i, j, bound = i[keep], j[keep], bound[keep]
    i, j = own[i], two[j]
    every = sets if other is None else [*sets, *other]
    j = j if other is None else j + len(sets)
    root = list(range(len(every)))

    def find(x: int) -> int:
        while root[x] != x:
            root[x] = root[root[x]]
            x = root[x]
        return x

    out = []
    for e in np.argsort(-bound, kind="stable"):
        a, b = int(i[e]), int(j[e])
        if (p := find(a)) != (q := find(b)) and linked(every[a], every[b], percent):
            root[max(p, q)] = min(p, q)
            out.append((a, b))
    return out


def _unpack(column) -> list[np.ndarray]:
    if isinstance(column, (pa.Array, pa.ChunkedArray)):
        column = column.to_pylist()
    return [np.frombuffer(x, np.uint64) for x in column]


LINKS = "u long, v long"


def _link_table(ids: np.ndarray, got: list[tuple[int, int]]) -> pa.RecordBatch:
    a, b = (np.array(x, np.int64) for x in zip(*got, strict=True)) if got else (np.zeros(0, np.int64),) * 2
    return pa.RecordBatch.from_arrays([pa.array(ids[a], pa.int64()), pa.array(ids[b], pa.int64())], ["u", "v"])


def can_link(docs: DataFrame, words: int, percent: int, total: int) -> tuple[DataFrame, DataFrame]:
    """(doc_id, n_shingles and digest c, d of every row; node and a doc_id of each set that may link)."""
    every = part_of_space(percent)
    buckets = max(12, -(-total // (BUCKET_BYTES * every)))
    told = materialise(docs.mapInArrow(K.lean(_tell(words, percent, buckets, every)), TOLD), "join-told")
    rows = told.where("kind = 0")
    spread = told.where("kind = 1").select("a", "piece", "blob").groupBy("a").applyInArrow(_shared_of_bucket, "piece long, row binary, n binary")
    shared = spread.groupBy("piece").applyInArrow(_shared_of_piece, "piece long, a long, shared long")
    own = rows.where("doc_id is not null and b > 0").select("piece", "a", "doc_id", "c", "need")
    able = own.where("need > 0").join(shared, ["piece", "a"]).where("shared >= need").select("doc_id", "c").unionByName(own.where("need <= 0").select("doc_id", "c"))
    able = materialise(able.groupBy(F.col("c").alias("node")).agg(F.min("doc_id").alias("doc_id")), "join-able")
    rows = materialise(rows.select("doc_id", F.col("b").alias("n_shingles"), "c", "d"), "join-rows")
    discard(told)
    return rows, able


def signature_tree_join(docs: DataFrame, words: int = 5, percent: int = 80, block: int = BLOCK) -> DataFrame:
    """(doc_id, n_shingles, component_id) for every row of docs(doc_id, text)."""
    docs = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    total = docs.agg(F.sum(F.octet_length("text"))).first()[0] or 0
    rows, able = can_link(docs, words, percent, total)
    some = docs.join(maybe_broadcast(able, able.count()), "doc_id").select("node", "text")
    sets = materialise(some.mapInArrow(K.lean(_sets(words)), "node long, n long, shingles binary").dropDuplicates(["node"]), "join-sets")
    buckets = max(12, -(-8 * (sets.agg(F.sum("n")).first()[0] or 0) // BUCKET_BYTES))
    signed = materialise(sets.select("node", "shingles").mapInArrow(K.lean(_signatures(percent, buckets)), SIGNED), "join-signed")
    far = signed.where("kind = 2").select("a", "blob").groupBy("a").applyInArrow(_forest_of_bucket, "node long, a long, n long")
    near = materialise(signed.where("kind = 1").select("node", "a", "n").unionByName(far), "join-near")
    cluster = connected_components(near.select(F.col("node").alias("u"), F.col("a").alias("v")))
    degree = near.groupBy("node").agg(F.sum("n").alias("degree"))
    size = materialise(cluster.groupBy("component").agg(F.count("*").alias("texts")), "join-size")
    members = cluster.join(maybe_broadcast(size, size.count()), "component").join(degree, "node", "left")
    members = materialise(members.select("node", F.col("component").alias("cluster"), F.coalesce("degree", F.lit(0)).alias("degree"), "texts"), "join-members")
    todo = materialise(sets.join(maybe_broadcast(members, members.count()), "node").select("cluster", "node", "degree", "texts", "n", "shingles"), "join-todo")
    discard(able, sets, signed, near, cluster, members)

    def within(t: pa.Table) -> pa.Table:
        return pa.Table.from_batches([_link_table(t.column("node").to_numpy(), tree_links(_unpack(t.column("shingles")), percent))])

    links = todo.where(F.col("texts") <= block).select("cluster", "node", "shingles").groupBy("cluster").applyInArrow(within, LINKS)
    spent = [size, todo]
    if size.where(F.col("texts") > block).limit(1).count():
        more, used = _large(todo.where(F.col("texts") > block).drop("texts"), percent, block)
        links = links.unionByName(more)
        spent += used
    links = materialise(links, "join-links")
    discard(*spent)
    found = connected_components(links)
    # of equal sets the smallest id speaks, and a component takes the smallest id of its sets
    heads = rows.where("doc_id is not null and n_shingles > 0").groupBy("c", "d").agg(F.min("doc_id").alias("low"), F.count("*").alias("copies"))
    named = found.select(F.col("node").alias("c"), "component")
    heads = heads.join(maybe_broadcast(named, named.count()), "c", "left").where("copies > 1 or component is not null")
    heads = materialise(heads.select("c", "d", "component", "low"), "join-heads")
    least = heads.where("component is not null").groupBy("component").agg(F.min("low").alias("least"))
    named = materialise(heads.join(least, "component", "left").select("c", "d", F.coalesce("least", "low").alias("component_id")), "join-named")
    discard(links, found, heads)
    # copies of one text may be a third of all rows: beyond a broadcast they are dealt by salt
    n = named.count()
    salts = 1 if n <= BROADCAST_ROWS else SALTS
    named = named.withColumn("salt", F.explode(F.sequence(F.lit(0), F.lit(salts - 1))))
    rows = rows.withColumn("salt", F.pmod(F.xxhash64("doc_id"), F.lit(salts)).cast("int"))
    return rows.join(maybe_broadcast(named, n), ["c", "d", "salt"], "left").select(
        "doc_id", "n_shingles", F.when(F.col("doc_id").isNotNull(), F.coalesce("component_id", "doc_id")).alias("component_id")
    )


# clusters of more than one block --------------------------------------------------


def _attach(percent: int):
    """Marks the sets that do not link with their cluster's leader, and gives each its smallest hash."""

    def run(batches):
        for b in batches:
            sets, lead = _unpack(b.column("shingles")), _unpack(b.column("lead_set"))
            alone = [not linked(x, y, percent) for x, y in zip(sets, lead, strict=True)]
            low = [int(K.mix(K.mix(s ^ K.STEP[13]).min(keepdims=True))[0] >> K.U(33)) for s in sets]
            cols = [b.column(c) for c in ("cluster", "node", "lead", "n", "shingles")]
            yield pa.RecordBatch.from_arrays([*cols, pa.array(alone, pa.bool_()), pa.array(low, pa.int64())], ["cluster", "node", "lead", "n", "shingles", "alone", "low"])

    return run


BLOCKS = "cluster long, band long, alone boolean, cut long, part long, small long, large long, spare long, bitmap binary, ids binary, sizes binary, sets binary"


def _pack_block(t: pa.Table) -> pa.Table:
    sets = _unpack(t.column("shingles"))
    size = np.array([len(s) for s in sets], np.int64)
    maps = bitmaps(sets, BLOCK_BITS)
    spare = int((size - np.bitwise_count(maps).sum(1, dtype=np.int64)).max())
    own = [t.column(c)[0].as_py() for c in ("cluster", "band", "alone", "cut", "part")]
    row = [*own, int(size.min()), int(size.max()), spare, np.bitwise_or.reduce(maps, axis=0).tobytes(), t.column("node").to_numpy().astype(np.int64).tobytes(), size.tobytes(), b"".join(s.tobytes() for s in sets)]
    kinds = [pa.int64(), pa.int64(), pa.bool_(), pa.int64(), pa.int64(), *(pa.int64(),) * 3, *(pa.binary(),) * 4]
    return pa.table([pa.array([x], k) for x, k in zip(row, kinds, strict=True)], names=[x.split()[0] for x in BLOCKS.split(", ")])


def _block_sets(ids: bytes, sizes: bytes, sets: bytes) -> tuple[np.ndarray, list[np.ndarray]]:
    return np.frombuffer(ids, np.int64), np.split(np.frombuffer(sets, np.uint64), np.cumsum(np.frombuffer(sizes, np.int64))[:-1])


def _or_maps(t: pa.Table) -> pa.Table:
    m = np.bitwise_or.reduce(np.stack([np.frombuffer(x, np.uint64) for x in t.column("bitmap").to_pylist()]), axis=0)
    f = lambda c, g: g(t.column(c).to_pylist())
    own = t.column("at")[0].as_py()
    row = [t.column("cluster")[0].as_py(), own // FANOUT, f("alone", any), f("small", min), f("large", max), f("spare", max), m.tobytes()]
    return pa.table([pa.array([x]) for x in row], names=["cluster", "at", "alone", "small", "large", "spare", "bitmap"])


def _prune(percent: int):
    """Node pairs whose bitmaps leave room for a link."""

    def run(batches):
        for b in batches:
            keep = []
            for mx, my, sx, sy, lx, ly, hx, hy in zip(*(b.column(c).to_pylist() for c in ("x_bitmap", "y_bitmap", "x_spare", "y_spare", "x_small", "y_small", "x_large", "y_large")), strict=True):
                both = int(np.bitwise_count(np.frombuffer(mx, np.uint64) & np.frombuffer(my, np.uint64)).sum(dtype=np.int64))
                keep.append(min(both + min(sx, sy), hx, hy) * (100 + percent) >= percent * (lx + ly))
            yield b.select(["cluster", "x_at", "y_at"]).filter(pa.array(keep, pa.bool_()))

    return run


def _block_links(percent: int):
    """Links of one pair of blocks."""

    def run(t: pa.Table) -> pa.Table:
        r = t.to_pylist()[0]
        ids, sets = _block_sets(r["x_ids"], r["x_sizes"], r["x_sets"])
        if r["x_at"] == r["y_at"]:
            return pa.Table.from_batches([_link_table(ids, tree_links(sets, percent))])
        ids2, sets2 = _block_sets(r["y_ids"], r["y_sizes"], r["y_sets"])
        return pa.Table.from_batches([_link_table(np.r_[ids, ids2], tree_links(sets, percent, sets2))])

    return run


def _large(sets: DataFrame, percent: int, block: int) -> tuple[DataFrame, list[DataFrame]]:
    """Links of clusters of more than ``block`` sets: to the leader, then along a tree of blocks."""
    leader = materialise(sets.groupBy("cluster").agg(F.max(F.struct("degree", "node")).alias("x")).select("cluster", F.col("x.node").alias("node")), "join-lead")
    lead = sets.join(leader, ["cluster", "node"]).select("cluster", F.col("node").alias("lead"), F.col("shingles").alias("lead_set"))
    if leader.count() <= LEADERS and (lead.agg(F.max(F.octet_length("lead_set"))).first()[0] or 0) <= LEADER_BYTES:
        rows = sets.join(F.broadcast(lead), "cluster")  # bounded by LEADERS * LEADER_BYTES
    else:
        lead = lead.withColumn("salt", F.explode(F.sequence(F.lit(0), F.lit(SALTS - 1))))
        rows = sets.withColumn("salt", F.pmod(F.xxhash64("node"), F.lit(SALTS)).cast("int")).join(lead, ["cluster", "salt"])
    rows = rows.select("cluster", "node", "lead", "n", "shingles", "lead_set").mapInArrow(_attach(percent), "cluster long, node long, lead long, n long, shingles binary, alone boolean, low long")
    rows = materialise(rows, "join-attached")
    linked_now = rows.where("not alone and node <> lead").select(F.col("node").alias("u"), F.col("lead").alias("v"))
    open_ = rows.groupBy("cluster").agg(F.max("alone").alias("open")).where("open").select("cluster")
    # a band of sizes is a run whose members can link with the same or the next band only
    ratio = 1.001 * math.log(100 / percent) if percent < 100 else 1e-9
    rest = rows.join(open_, "cluster", "left_semi").withColumn("band", F.floor(F.log("n") / F.lit(ratio)))
    # runs of the smallest hash keep alike sets in one block; a run of very many alike sets is dealt by hash
    cuts = lambda: F.ceil(F.greatest(F.count("*") / F.lit(block), F.sum("n") * 8 / F.lit(BLOCK_BYTES)))
    keys = ["cluster", "band", "alone"]
    first = materialise(rest.groupBy(*keys).agg(cuts().alias("cuts")), "join-cuts")
    rest = rest.join(maybe_broadcast(first, first.count(), 100_000), keys).withColumn("cut", F.expr("(low * cuts) div 2147483648")).drop("cuts")
    second = materialise(rest.groupBy(*keys, "cut").agg(cuts().alias("parts")), "join-parts")
    rest = rest.join(maybe_broadcast(second, second.count(), 100_000), [*keys, "cut"]).withColumn("part", F.pmod(F.xxhash64("node"), F.col("parts")))
    blocks = materialise(rest.select(*keys, "cut", "part", "node", "shingles").groupBy(*keys, "cut", "part").applyInArrow(_pack_block, BLOCKS), "join-blocks")
    place = F.row_number().over(Window.partitionBy("cluster").orderBy("band", "cut", "part", "alone")) - 1
    at = materialise(blocks.select(*keys, "cut", "part").withColumn("at", place.cast("long")), "join-places")
    blocks = blocks.join(maybe_broadcast(at, at.count(), 100_000), [*keys, "cut", "part"])
    leaf = materialise(blocks.select("cluster", "at", "alone", "small", "large", "spare", "bitmap"), "join-leaves")
    levels, most = [leaf], at.agg(F.max("at")).first()[0] or 0
    while most >= 1:
        up = levels[-1].withColumn("up", F.expr(f"at div {FANOUT}")).groupBy("cluster", "up").applyInArrow(lambda t: _or_maps(t.drop(["up"])), leaf.schema)
        levels.append(materialise(up, "join-level"))
        most //= FANOUT
    tops = levels[-1].select("cluster", F.col("at").alias("x_at"), F.col("at").alias("y_at"))
    spent = [leader, rows, first, second, at, *levels]
    pairs = tops
    for k in range(len(levels) - 1, -1, -1):
        side = lambda s: levels[k].select("cluster", *(F.col(c).alias(f"{s}_{c}") for c in levels[k].columns if c != "cluster"))  # noqa: B023, E731
        if k < len(levels) - 1:  # children of the pairs that survived
            step = F.explode(F.sequence(F.lit(0), F.lit(FANOUT - 1)))
            pairs = pairs.withColumn("i", step).withColumn("j", step).select("cluster", (F.col("x_at") * FANOUT + F.col("i")).alias("x_at"), (F.col("y_at") * FANOUT + F.col("j")).alias("y_at")).where("x_at <= y_at")
        pairs = pairs.join(side("x"), ["cluster", "x_at"]).join(side("y"), ["cluster", "y_at"])
        pairs = pairs.where(f"(x_alone or y_alone) and 100 * x_large >= {percent} * y_small and 100 * y_large >= {percent} * x_small")
        pairs = materialise(pairs.mapInArrow(_prune(percent), "cluster long, x_at long, y_at long"), "join-pairs")
        spent.append(pairs)
    pay = lambda s: blocks.select("cluster", *(F.col(c).alias(f"{s}_{c}") for c in ("at", "ids", "sizes", "sets")))
    both = pairs.join(pay("x"), ["cluster", "x_at"]).join(pay("y"), ["cluster", "y_at"])
    return linked_now.unionByName(both.groupBy("cluster", "x_at", "y_at").applyInArrow(_block_links(percent), LINKS)), [*spent, blocks]


def op8_signature_tree_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Three-word shingles, similarity 0.9, over all documents."""
    return signature_tree_join(table(spark, sf_dir, "documents"), words=3, percent=90)


def keep_first_of_component(docs: DataFrame, words: int = 5, percent: int = 80) -> DataFrame:
    """Documents whose id is the smallest of its component; of repeated rows of an id one stays, rows without id all stay."""
    found = signature_tree_join(docs, words, percent).where("component_id is null or component_id = doc_id")
    ids = materialise(found.groupBy("doc_id").agg(F.count("*").alias("times")), "join-first")
    once, twice = ids.where("times = 1 or doc_id is null").select("doc_id"), ids.where("times > 1 and doc_id is not null").select("doc_id")
    more = twice.count()
    kept = docs.join(maybe_broadcast(once, ids.count() - more), docs["doc_id"].eqNullSafe(once["doc_id"]), "left_semi")
    if not more:
        return kept
    return kept.unionByName(docs.join(maybe_broadcast(twice, more), "doc_id", "left_semi").dropDuplicates(["doc_id"]).select(*docs.columns))
