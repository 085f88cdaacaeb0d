"""SimHash near-duplicates through Golay fuzzy keys.

A fingerprint bit is the majority of that bit over the XXH64 hashes of the text's
features.  The 64 bits are cut into three segments (21, 21 and 22 bits) with the keys

* the raw segment and a Golay index of another one, for each ordered pair of segments;
* Golay indices of all three.

Four errors over three segments leave either a segment without error and another with at most two (a key of the
first kind is shared), or one or two errors in each (a key of the second kind is), so fingerprints within
four bits always share a key.  Equal fingerprints are one node.  Nodes with a common
key meet in a task and are verified; the task returns only a spanning star of each
component that it finds, never all pairs.  A key bucket over ``bucket_bytes`` is dealt over a grid of
cells, so that each two of its nodes still meet in one.

``near_components`` links 64-bit fingerprints of word shingles within four bits.  ``near_groups`` finds the
components of all pairs whose five-word shingles agree to ``similarity``, exactly:

1. Three fingerprints of the set of words (an edited word moves one feature there, not five), keys of the first kind alone and
   links within ``distance`` of 192 bits give most pairs.  A link counts only if all shingle hashes of both texts agree.
2. Fingerprints cannot prove that no pair is missed, so the rest is found by prefixes: of n hashes in one common order, the
   first n - ceil(similarity * n) + 1 hold one that a similar text has in its own.  Pairs of different groups that
   share one are ruled out by their sizes and by parity bitmaps (bounds, not estimates), or compared in full.
3. Where an edge of step 2 fails, all pairs of different groups are compared that the bounds leave.

Defined results: null text is empty; a text without words has fingerprint zero and is linked like any other;
fewer words than a shingle has are one shingle; repeated rows keep their rows; null ids are the smallest; other columns are ignored.
"""

from __future__ import annotations

import math

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import cut, lean, text_chunks, texts
from .golay import indices
from .graph import components
from .sketches import WORDS

SEED = 42
DISTANCE = 4
SEGMENTS = ((0, 21), (21, 21), (42, 22))


def _majority(hashes: np.ndarray) -> int:
    ones, n = np.zeros(64, np.int64), len(hashes)
    for at in range(0, n, 1 << 16):
        ones += np.unpackbits(hashes[at : at + (1 << 16)].view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(0, dtype=np.int64)
    return int.from_bytes(np.packbits(ones * 2 > n, bitorder="little").tobytes(), "little")


def shingle_hashes(own: list[bytes], words: int) -> np.ndarray:
    """XXH64 of all shingles of a list of words, repeats included."""
    import xxhash

    if not own:
        return np.zeros(0, np.uint64)
    n = max(1, len(own) - words + 1)
    start = np.concatenate([[0], np.cumsum(np.fromiter(map(len, own), np.int64, len(own)) + 1)])
    joined = b" ".join(own)
    ends = (start[np.minimum(np.arange(n) + words, len(own))] - 1).tolist()
    digest = xxhash.xxh64_intdigest
    return np.fromiter((digest(joined[a:b], SEED) for a, b in zip(start.tolist(), ends)), np.uint64, n)


def simhash(text: str, words: int) -> int:
    hashes = shingle_hashes(text.encode().lower().split(), words)
    return _majority(hashes) if len(hashes) else 0


def fingerprints(docs: DataFrame, words: int = 4) -> DataFrame:
    """doc_id, fps (8 bytes, little-endian)."""

    def run(batches):
        import pyarrow as pa

        for batch in batches:
            for part in text_chunks(batch, 8_000_000):
                fps = [simhash(t, words).to_bytes(8, "little") for t in part.column(1).to_pylist()]
                yield pa.RecordBatch.from_arrays([part.column(0), pa.array(fps, pa.binary())], ["doc_id", "fps"])

    return texts(docs).mapInArrow(lean(run), "doc_id long, fps binary")


BITS = 1024  # of the parity bitmap: bit i is the parity of how many of a text's shingle hashes fall on i
WIDE = 4 * BITS  # for texts of more than LONG shingles, where the short bitmap would rule nothing out
LONG = 1000
NULL_ID = -(2**63)


def shingle_set(text: str, words: int = WORDS) -> np.ndarray:
    """Distinct shingle hashes, ascending."""
    return np.unique(shingle_hashes(text.encode().lower().split(), words))


def prefix(hashes: np.ndarray, similarity: float, common: np.ndarray) -> np.ndarray:
    """The first n - ceil(similarity * n) + 1 hashes, those in ``common`` last: two sets of at least ``similarity`` share one of these."""
    if not len(hashes):
        return hashes
    late = common[np.minimum(np.searchsorted(common, hashes), len(common) - 1)] == hashes if len(common) else np.zeros(len(hashes), bool)
    return np.concatenate([hashes[~late], hashes[late]])[: len(hashes) - math.ceil(similarity * len(hashes) - 1e-9) + 1]


def parity(hashes: np.ndarray, bits: int = BITS) -> bytes:
    """Two bitmaps differ in at most as many bits as their sets have hashes that the other one lacks."""
    return np.packbits(np.bincount((hashes % np.uint64(bits)).astype(np.int64), minlength=bits) & 1).tobytes()


def folded(bitmap: bytes, bits: int) -> bytes:
    """The same bitmap at ``bits``, at most its own width."""
    return np.bitwise_xor.reduce(np.frombuffer(bitmap, np.uint8).reshape(-1, bits // 8)).tobytes()


def common_shingles(docs: DataFrame, words: int, sample_bytes: int = 6_000_000, least: int = 4) -> np.ndarray:
    """Shingle hashes of several texts of a sample.  They only order the prefixes: any set gives the same groups."""
    rows = texts(docs)
    total = rows.agg(F.sum(F.octet_length("text")).alias("b")).first()["b"] or 0
    share = min(1_000_000, int(1_000_000 * sample_bytes / max(1, total)) + 1)

    def run(batches):
        import pyarrow as pa

        for batch in batches:
            for part in text_chunks(batch, 8_000_000):
                yield pa.RecordBatch.from_arrays([pa.array(np.concatenate([shingle_set(t, words) for t in part.column(1).to_pylist()]).view(np.int64))], ["h"])

    found = rows.filter(F.pmod(F.xxhash64("doc_id"), F.lit(1_000_000)) < share).mapInArrow(lean(run), "h long").groupBy("h").count().filter(F.col("count") >= least).select("h")
    return np.sort(np.asarray(found.toArrow().column("h")).astype(np.int64).view(np.uint64))


def word_set_fingerprints(docs: DataFrame, count: int = 3, words: int = WORDS, similarity: float = 0.8, common: np.ndarray = np.zeros(0, np.uint64)) -> DataFrame:
    """rep (id, null as the smallest), fps (``count`` fingerprints of the set of words), n (distinct shingles), bits (parity bitmap), keys (prefix of the shingle hashes)."""

    def run(batches):
        import pyarrow as pa
        import xxhash

        for batch in batches:
            for part in text_chunks(batch, 8_000_000):
                fps, sizes, bits, keys = [], [], [], []
                for t in part.column(1).to_pylist():
                    own = t.encode().lower().split()
                    bag = np.fromiter((xxhash.xxh64_intdigest(w, SEED) for w in set(own)), np.uint64)
                    bag, raw = _scramble(bag), b""
                    for _ in range(count):
                        raw += (_majority(bag) if len(bag) else 0).to_bytes(8, "little")
                        bag = _scramble(bag)
                    fps.append(raw)
                    h = np.unique(shingle_hashes(own, words))
                    sizes.append(len(h))
                    bits.append(parity(h, WIDE if len(h) >= similarity * LONG - 1 else BITS))
                    keys.append(prefix(h, similarity, common).tobytes())
                yield pa.RecordBatch.from_arrays([part.column(0).fill_null(NULL_ID), pa.array(fps, pa.binary()), pa.array(sizes, pa.int64()), pa.array(bits, pa.binary()), pa.array(keys, pa.binary())], ["rep", "fps", "n", "bits", "keys"])

    return texts(docs).mapInArrow(lean(run), "rep long, fps binary, n long, bits binary, keys binary")


def _scramble(x: np.ndarray) -> np.ndarray:
    x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


def fuzzy_keys(fp: np.ndarray, triples: bool = True) -> tuple[np.ndarray, np.ndarray]:
    """(key, row of fp) for all keys of all fingerprints."""
    seg = [((fp >> np.uint64(at)) & np.uint64((1 << bits) - 1)).astype(np.int64) for at, bits in SEGMENTS]
    near = [indices(s) for s in seg]
    rows = np.arange(len(fp))
    keys, at = [], []
    for x in range(3):
        for y in range(3):
            if x != y:
                k = (np.int64(3 * x + y) << 56) | (seg[x][:, None] << 12) | near[y]
                ok = near[y] >= 0
                keys.append(k[ok])
                at.append(np.broadcast_to(rows[:, None], k.shape)[ok])
    if triples:
        k = (np.int64(9) << 56) | (near[0][:, :, None, None] << 24) | (near[1][:, None, :, None] << 12) | near[2][:, None, None, :]
        ok = (near[0] >= 0)[:, :, None, None] & (near[1] >= 0)[:, None, :, None] & (near[2] >= 0)[:, None, None, :]
        keys.append(k[ok])
        at.append(np.broadcast_to(rows[:, None, None, None], k.shape)[ok])
    return np.concatenate(keys), np.concatenate(at)


def key_blobs(nodes: DataFrame, n_buckets: int, grid: dict[int, int] | None = None, triples: bool = True, chunk: int = 8192) -> DataFrame:
    """(bucket, cell, blob): keys with their nodes; a bucket in ``grid`` goes to cells (i, j), i <= j, of a grid."""
    grid = grid or {}

    def emit(rep: np.ndarray, fps: np.ndarray):
        import pyarrow as pa

        parts = [fuzzy_keys(fps[:, f], triples) for f in range(fps.shape[1])]
        key = np.concatenate([k | (np.int64(f) << 60) for f, (k, _) in enumerate(parts)])
        row = np.concatenate([r for _, r in parts])
        bucket = (_scramble(key.view(np.uint64)) % np.uint64(n_buckets)).astype(np.int64)
        order = np.argsort(bucket, kind="stable")
        ends = np.searchsorted(bucket[order], np.arange(n_buckets + 1))
        out: tuple[list, list, list] = ([], [], [])
        for b in np.flatnonzero(np.diff(ends)).tolist():
            pick = order[ends[b] : ends[b + 1]]
            g = grid.get(b, 1)
            lane = _scramble(rep[row[pick]].view(np.uint64)) % np.uint64(g)
            for i in range(g):
                mine = pick[lane == i] if g > 1 else pick
                if len(mine):
                    own, at = np.unique(row[mine], return_inverse=True)
                    blob = np.array([len(own), len(mine)], "<i8").tobytes() + rep[own].tobytes() + fps[own].tobytes() + key[mine].tobytes() + at.astype("<u4").tobytes()
                    for j in range(g):
                        out[0].append(b)
                        out[1].append(min(i, j) * g + max(i, j))
                        out[2].append(blob)
        return pa.RecordBatch.from_arrays([pa.array(out[0], pa.int64()), pa.array(out[1], pa.int64()), pa.array(out[2], pa.binary())], ["bucket", "cell", "blob"])

    def run(batches):
        for batch in batches:
            rep = np.asarray(batch.column(0).fill_null(-(2**63)))
            fps = np.frombuffer(b"".join(batch.column(1).to_pylist()), "<u8").reshape(len(rep), -1) if len(rep) else None
            for at in range(0, len(rep), chunk):
                yield emit(rep[at : at + chunk], fps[at : at + chunk])

    return nodes.select("rep", "fps").mapInArrow(lean(run), "bucket long, cell long, blob binary")


class Forest:
    """Labels of a task's nodes: the smallest node linked to each."""

    def __init__(self, n: int):
        self.label = np.arange(n)

    def link(self, a: np.ndarray, b: np.ndarray) -> None:
        while len(a):
            la, lb = self.label[a], self.label[b]
            odd = la != lb
            a, b, la, lb = a[odd], b[odd], la[odd], lb[odd]
            if not len(a):
                return
            np.minimum.at(self.label, np.maximum(la, lb), np.minimum(la, lb))
            while not np.array_equal(nxt := self.label[self.label], self.label):
                self.label = nxt


def spanning_stars(key: np.ndarray, at: np.ndarray, rep: np.ndarray, fps: np.ndarray, distance: int, small: int = 12) -> tuple[np.ndarray, np.ndarray]:
    """(u, v): nodes and the smallest one they are linked to, by verified pairs of equal key.  ``rep`` ascends."""

    def close(x, y):
        return np.bitwise_count(fps[x] ^ fps[y]).sum(-1) <= distance

    order = np.lexsort((at, key))
    key, at = key[order], at[order]
    again = np.concatenate([[True], (key[1:] != key[:-1]) | (at[1:] != at[:-1])])
    key, at = key[again], at[again]
    first = np.flatnonzero(np.concatenate([[True], key[1:] != key[:-1]]))
    size = np.diff(np.append(first, len(key)))
    forest = Forest(len(rep))
    pick = np.repeat((size <= small) & (size > 1), size)
    k, a = key[pick], at[pick]
    for step in range(1, small):
        same = np.flatnonzero(k[step:] == k[:-step]) if len(k) > step else ()
        if not len(same):
            break
        x, y = a[same], a[same + step]
        ok = close(x, y)
        forest.link(x[ok], y[ok])
    for r in sorted(np.flatnonzero(size > small).tolist(), key=lambda r: -size[r]):
        left = at[first[r] : first[r] + size[r]]
        label = forest.label[left]
        if (label == label[0]).all():
            continue
        x: list[int] = []
        y: list[int] = []
        queue: list[int] = []
        while len(left):  # what a node reaches leaves the run, so dense runs shrink at once
            if not queue:
                queue, left = [int(left[0])], left[1:]
                continue
            here = queue.pop()
            ok = close(left, here)
            got = left[ok].tolist()
            x += [here] * len(got)
            y += got
            queue += got
            left = left[~ok]
        forest.link(np.array(x, np.int64), np.array(y, np.int64))
    moved = np.flatnonzero(forest.label != np.arange(len(rep)))
    return rep[moved], rep[forest.label[moved]]


def _unblob(blobs: list[bytes]):
    reps, fps, keys, ats, base = [], [], [], [], 0
    for b in blobs:
        n, m = np.frombuffer(b, "<i8", 2).tolist()
        reps.append(np.frombuffer(b, "<i8", n, 16))
        width = (len(b) - 16 - 8 * n - 12 * m) // 8
        fps.append(np.frombuffer(b, "<u8", width, 16 + 8 * n).reshape(n, -1))
        keys.append(np.frombuffer(b, "<i8", m, 16 + 8 * n + 8 * width))
        ats.append(np.frombuffer(b, "<u4", m, 16 + 8 * n + 8 * width + 8 * m).astype(np.int64) + base)
        base += n
    rep, first, inverse = np.unique(np.concatenate(reps), return_index=True, return_inverse=True)
    return np.concatenate(keys), inverse[np.concatenate(ats)], rep, np.concatenate(fps)[first]


def links(nodes: DataFrame, *, distance: int = DISTANCE, triples: bool = True, width: int = 1, bucket_bytes: int = 48_000_000) -> DataFrame:
    """(u, v): edges whose components are those of all nodes (rep, fps) that share a key and lie within ``distance``."""
    per_node = width * (181 if triples else 32) * 16
    n_buckets = max(12, -(-nodes.count() * per_node // (bucket_bytes // 2)))
    sizes = key_blobs(nodes, n_buckets, None, triples).groupBy("bucket").agg(F.sum(F.octet_length("blob")).alias("b")).filter(F.col("b") > bucket_bytes)
    grid = {r["bucket"]: -(-2 * r["b"] // bucket_bytes) for r in sizes.collect()}  # at most total / bucket_bytes rows

    def meet(table):
        import pyarrow as pa

        u, v = spanning_stars(*_unblob(table.column("blob").to_pylist()), distance)
        return pa.table({"u": pa.array(u), "v": pa.array(v)})

    return key_blobs(nodes, n_buckets, grid, triples).groupBy("bucket", "cell").applyInArrow(lean(meet), "u long, v long")


def _nodes(rows: DataFrame) -> DataFrame:
    return cut(rows.groupBy("fps").agg(F.min(F.coalesce("doc_id", F.lit(-(2**63)))).alias("rep")))


def _named(nodes: DataFrame, edges: DataFrame) -> DataFrame:
    """(__f, component_id) for every node."""
    named = nodes.join(components(edges), F.col("rep") == F.col("node"), "left").select(F.col("fps").alias("__f"), F.coalesce("root", "rep").alias("c"))
    return cut(named.select("__f", F.when(F.col("c") > -(2**63), F.col("c")).alias("component_id")))


def near_components(docs: DataFrame, *, words: int = 4, bucket_bytes: int = 48_000_000) -> DataFrame:
    """doc_id, fingerprint (16 hex digits), component_id (smallest doc_id that links lead to, its own included)."""
    rows = cut(fingerprints(docs, words))
    nodes = _nodes(rows)
    named = _named(nodes, links(nodes, bucket_bytes=bucket_bytes))
    return rows.join(named, F.col("fps") == F.col("__f")).select("doc_id", F.lower(F.hex(_reversed("fps"))).alias("fingerprint"), "component_id")


def _reversed(col: str):
    """The eight bytes in reverse order."""
    return F.concat(*[F.expr(f"substring({col}, {k}, 1)") for k in range(8, 0, -1)])


def _node(bits: int) -> np.dtype:
    return np.dtype([("rep", "<i8"), ("label", "<i8"), ("n", "<i8"), ("bits", "<u8", bits // 64)])


def _dealt_keys(n_buckets: int, bits: int = 0, chunk: int = 8192):
    """Rows (rep, keys) or, for bitmaps of ``bits``, (rep, keys, label, n, bits) -> (bucket, blob): keys with their nodes."""

    def emit(batch):
        import pyarrow as pa

        raw = batch.column("keys").to_pylist()
        node = np.zeros(len(raw), _node(bits)) if bits else np.zeros(len(raw), "<i8")
        ids = np.asarray(batch.column("rep"))
        if bits:
            node["rep"], node["label"], node["n"] = ids, np.asarray(batch.column("label")), np.asarray(batch.column("n"))
            node["bits"] = np.frombuffer(b"".join(folded(x, bits) for x in batch.column("bits").to_pylist()), "<u8").reshape(len(raw), -1)
        else:
            node[:] = ids
        key = np.frombuffer(b"".join(raw), "<u8")
        at = np.repeat(np.arange(len(raw)), [len(x) // 8 for x in raw])
        bucket = (_scramble(key) % np.uint64(n_buckets)).astype(np.int64)
        order = np.argsort(bucket, kind="stable")
        ends = np.searchsorted(bucket[order], np.arange(n_buckets + 1))
        out: tuple[list, list] = ([], [])
        for b in np.flatnonzero(np.diff(ends)).tolist():
            pick = order[ends[b] : ends[b + 1]]
            own, local = np.unique(at[pick], return_inverse=True)
            out[0].append(b)
            out[1].append(np.array([len(own), len(pick)], "<i8").tobytes() + node[own].tobytes() + key[pick].tobytes() + local.astype("<u4").tobytes())
        return pa.RecordBatch.from_arrays([pa.array(out[0], pa.int64()), pa.array(out[1], pa.binary())], ["bucket", "blob"])

    def run(batches):
        for batch in batches:
            for at in range(0, batch.num_rows, chunk):
                yield emit(batch.slice(at, chunk))

    return run


def _met_keys(blobs: list[bytes], kind) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(key, row of nodes, nodes) of the keys that several nodes of a bucket have, by key."""
    nodes, keys, ats, base, size = [], [], [], 0, np.dtype(kind).itemsize
    for b in blobs:
        n, m = np.frombuffer(b, "<i8", 2).tolist()
        nodes.append(np.frombuffer(b, kind, n, 16))
        keys.append(np.frombuffer(b, "<u8", m, 16 + n * size))
        ats.append(np.frombuffer(b, "<u4", m, 16 + n * size + 8 * m).astype(np.int64) + base)
        base += n
    key, at, node = np.concatenate(keys), np.concatenate(ats), np.concatenate(nodes)
    order = np.argsort(key, kind="stable")
    key, at = key[order], at[order]
    again = np.concatenate([[False], key[1:] == key[:-1]])
    again[:-1] |= again[1:]
    return key[again], at[again], node


def _repeated(table):
    """Bucket -> (rep, keys): of each node the keys that others have too."""
    import pyarrow as pa

    key, at, node = _met_keys(table.column("blob").to_pylist(), "<i8")
    order = np.argsort(at, kind="stable")
    key, at = key[order], at[order]
    own, first = np.unique(at, return_index=True)
    ends = np.append(first, len(at)).tolist()
    return pa.table({"rep": pa.array(node[own], pa.int64()), "keys": pa.array([key[a:b].tobytes() for a, b in zip(ends[:-1], ends[1:])], pa.binary())})


def hooks(label: np.ndarray, x: np.ndarray, y: np.ndarray) -> np.ndarray:
    """Places of edges (x, y) that suffice to connect what all of them and equal labels do; ``label`` is changed to the new components."""
    used = [np.zeros(0, np.int64)]
    at = np.arange(len(x))
    while len(at):
        a, b = label[x[at]], label[y[at]]
        odd = a != b
        at, low, high = at[odd], np.minimum(a, b)[odd], np.maximum(a, b)[odd]
        if not len(at):
            break
        order = np.lexsort((low, high))
        first = order[np.concatenate([[True], high[order][1:] != high[order][:-1]])]
        used.append(at[first])
        up = np.arange(len(label))
        up[high[first]] = low[first]
        while not np.array_equal(nxt := up[up], up):
            up = nxt
        label[:] = up[label]
    return np.concatenate(used)


def _within(similarity: float, every: bool, width: int, small: int = 12):
    """Bucket -> (u, v): pairs of different labels with a common key whose sizes and bitmaps do not rule ``similarity`` out: all or enough to connect them."""
    rate, kind = (1 - similarity) / (1 + similarity), _node(width)

    def run(table):
        import pyarrow as pa

        key, at, node = _met_keys(table.column("blob").to_pylist(), kind)
        own, at_own = np.unique(np.frombuffer(node.tobytes(), f"V{kind.itemsize}"), return_inverse=True)
        node, at = np.frombuffer(own.tobytes(), kind), at_own.ravel()[at]
        n, bits = node["n"], node["bits"]
        label = np.unique(node["label"], return_inverse=True)[1].ravel()
        first_label = label.copy()

        def close(x, y):
            both = n[x] + n[y]
            return (np.minimum(n[x], n[y]) >= similarity * np.maximum(n[x], n[y]) - 1e-9) & (np.bitwise_count(bits[x] ^ bits[y]).sum(-1, dtype=np.int64) <= rate * both + 1e-9)

        order = np.lexsort((at, n[at], key))
        key, at = key[order], at[order]
        fresh = np.concatenate([[True], (key[1:] != key[:-1]) | (at[1:] != at[:-1])]) if len(key) else np.zeros(0, bool)
        key, at = key[fresh], at[fresh]
        first = np.flatnonzero(np.concatenate([[True], key[1:] != key[:-1]])) if len(key) else np.zeros(0, np.int64)
        size = np.diff(np.append(first, len(key)))
        xs, ys = [np.zeros(0, np.int64)], [np.zeros(0, np.int64)]
        pick = np.repeat((size <= small) & (size > 1), size)
        k, a = key[pick], at[pick]
        for step in range(1, small):
            same = np.flatnonzero((k[step:] == k[:-step]) & (label[a[step:]] != label[a[:-step]])) if len(k) > step else ()
            if not len(same):
                continue
            x, y = a[same], a[same + step]
            ok = close(x, y)
            xs.append(x[ok])
            ys.append(y[ok])
        seen = set()
        for r in np.flatnonzero(size > small).tolist():
            left = at[first[r] : first[r] + size[r]]
            if (label[left] == label[left[0]]).all() or (mark := left.tobytes()) in seen:
                continue
            seen.add(mark)
            queue: list[int] = []
            while len(left):
                if every or not queue:
                    here, left = int(left[0]), left[1:]
                else:
                    here = queue.pop()
                lo = np.searchsorted(n[left], similarity * n[here] - 1e-9)
                hi = np.searchsorted(n[left], n[here] / similarity + 1e-9, side="right")
                near = left[lo:hi]
                ok = close(near, here)
                got = near[ok]
                if every:
                    got = got[label[got] != label[here]]
                else:  # what a node reaches leaves the run, so dense runs shrink at once
                    queue += got.tolist()
                    left = np.concatenate([left[:lo], near[~ok], left[hi:]])
                xs.append(np.full(len(got), here))
                ys.append(got)
        pair = np.unique(np.stack([np.concatenate(xs), np.concatenate(ys)]), axis=1)
        x, y = pair[:, first_label[pair[0]] != first_label[pair[1]]] if every else pair[:, hooks(label, *pair)]
        u, v = node["rep"][x], node["rep"][y]
        return pa.table({"u": pa.array(np.maximum(u, v)), "v": pa.array(np.minimum(u, v))})

    return run


def _held(ids: DataFrame) -> np.ndarray:
    """Bitmap of at most 4 MB over hashes of the ids (u)."""
    m = 1 << min(25, max(10, (16 * ids.count()).bit_length()))

    def run(batches):
        import pyarrow as pa

        for batch in batches:
            p = (_scramble(np.asarray(batch.column(0)).view(np.uint64)) % np.uint64(m)).astype(np.int64)
            yield pa.RecordBatch.from_arrays([pa.array(p >> 5), pa.array(np.int64(1) << (p & 31))], ["word", "bit"])

    got = ids.mapInArrow(lean(run), "word long, bit long").groupBy("word").agg(F.bit_or("bit").alias("bit")).toArrow()
    out = np.zeros(m >> 5, np.uint32)
    out[np.asarray(got.column("word"))] = np.asarray(got.column("bit")).astype(np.uint32)
    return out


def verified(docs: DataFrame, edges: DataFrame, similarity: float, words: int = WORDS) -> DataFrame:
    """(u, v, ok) of distinct edges: whether all distinct shingle hashes of both texts agree to ``similarity``."""
    edges = cut(edges.distinct())
    held = _held(edges.select("u").unionByName(edges.select(F.col("v").alias("u"))).distinct())

    def sets(batches):
        import pyarrow as pa

        for batch in batches:
            ids = np.asarray(batch.column(0).fill_null(NULL_ID))
            p = (_scramble(ids.view(np.uint64)) % np.uint64(32 * len(held))).astype(np.int64)
            few = pa.RecordBatch.from_arrays([pa.array(ids), batch.column(1)], ["doc_id", "text"]).filter(pa.array((held[p >> 5] >> (p & 31).astype(np.uint32)) & 1 == 1))
            for part in text_chunks(few, 4_000_000):
                yield pa.RecordBatch.from_arrays([part.column(0), pa.array([shingle_set(t, words).tobytes() for t in part.column(1).to_pylist()], pa.binary())], ["id", "hashes"])

    def judge(batches):
        import pyarrow as pa

        for batch in batches:
            ok = []
            for a, b in zip(batch.column("a").to_pylist(), batch.column("b").to_pylist()):
                a, b = np.frombuffer(a, "<u8"), np.frombuffer(b, "<u8")
                both = len(np.intersect1d(a, b, assume_unique=True))
                union = len(a) + len(b) - both
                ok.append((both / union if union else 1.0) >= similarity)
            yield pa.RecordBatch.from_arrays([batch.column("u"), batch.column("v"), pa.array(ok, pa.bool_())], ["u", "v", "ok"])

    full = cut(texts(docs).mapInArrow(lean(sets), "id long, hashes binary"))
    pairs = edges.join(full.select(F.col("id").alias("__a"), F.col("hashes").alias("a")), F.col("u") == F.col("__a")).drop("__a")
    pairs = pairs.join(full.select(F.col("id").alias("__b"), F.col("hashes").alias("b")), F.col("v") == F.col("__b")).select("u", "v", "a", "b")
    return cut(pairs.mapInArrow(lean(judge), "u long, v long, ok boolean"))


def near_groups(docs: DataFrame, *, similarity: float = 0.8, count: int = 3, distance: int = 20, bucket_bytes: int = 48_000_000) -> DataFrame:
    """(doc_id, keep_id) of the documents that are not the smallest id of their component of pairs that agree to ``similarity``."""
    rows = cut(word_set_fingerprints(docs, count, similarity=similarity, common=common_shingles(docs, WORDS)))
    nodes = cut(rows.groupBy("fps").agg(F.min("rep").alias("rep")))
    same = rows.select(F.col("rep").alias("u"), "fps").join(nodes.select(F.col("fps").alias("__f"), F.col("rep").alias("v")), F.col("fps") == F.col("__f")).select("u", "v")
    edges = links(nodes, distance=distance, triples=False, width=count, bucket_bytes=bucket_bytes).unionByName(same).filter("u <> v")
    sure = verified(docs, edges, similarity).filter("ok").select("u", "v")

    size = rows.agg(F.sum(F.octet_length("keys")).alias("b")).first()["b"] or 0
    n_buckets = max(12, -(-2 * size // (bucket_bytes // 2)))
    blobs = "bucket long, blob binary"
    shared = cut(rows.select("rep", "keys").mapInArrow(lean(_dealt_keys(n_buckets)), blobs).groupBy("bucket").applyInArrow(lean(_repeated), "rep long, keys binary"))
    for every in (False, True):
        group = components(sure)
        known = rows.select(F.col("rep").alias("__r"), "n", "bits").join(group, F.col("__r") == F.col("node"), "left").select("__r", "n", "bits", F.coalesce("root", "__r").alias("label"))
        met = shared.join(known, F.col("rep") == F.col("__r")).select("rep", "keys", "label", "n", "bits")
        met = cut(met)
        # a pair of similar texts is in the first part or, if one has more than LONG shingles, in the second
        parts = [(met.filter(F.col("n") <= LONG), BITS), (met.filter(F.col("n") >= similarity * LONG), WIDE)]
        found = [part.mapInArrow(lean(_dealt_keys(n_buckets, bits)), blobs).groupBy("bucket").applyInArrow(lean(_within(similarity, every, bits)), "u long, v long") for part, bits in parts]
        tried = verified(docs, found[0].unionByName(found[1]).filter("u <> v"), similarity)
        sure = cut(sure.unionByName(tried.filter("ok").select("u", "v")))
        if tried.filter("not ok").isEmpty():  # else a pair may hang on an edge that failed: all pairs of different groups follow
            break
    return components(sure).select(F.col("node").alias("doc_id"), F.when(F.col("root") > NULL_ID, F.col("root")).alias("keep_id"))


def drop_near(docs: DataFrame, **options) -> DataFrame:
    """All columns of the documents that stay: of each group of near copies the smallest doc_id."""
    keep = docs.columns
    gone = cut(near_groups(docs, **options).select(F.col("doc_id").alias("__gone")).distinct())
    return docs.join(gone, docs["doc_id"].eqNullSafe(F.col("__gone")), "left_anti").select(*[docs[c] for c in keep])
