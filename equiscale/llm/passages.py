"""Removal of passages that repeat across documents, by suffix arrays in shards.

Every byte goes that is covered by a ``length``-byte string which also starts in a document with a smaller id.

1. Documents are dealt into shards by a hash of their id (the only time that texts shuffle; later steps reuse the exchange).
2. Every window of ``length`` bytes has one anchor: the ``gram`` bytes in it with the smallest hash (the first of several).
   Equal windows have equal anchors.  Neighbouring windows with one anchor are one context.
3. Shards exchange thin digests of their anchors.  An anchor of one document alone repeats nowhere and is done with.  Digests
   only choose candidates; from here on bytes decide.
4. Each shard deals the bytes of its other contexts into suffix shards by anchor, equal contexts (compared by their bytes)
   once.  There equal contexts of all shards become one; if it is the only one of its anchor, nothing else can share a window with it.  An anchor with more than ``hot_contexts`` contexts is split: its windows are dealt by most of their own bytes, so
   that a frequent header's surroundings go to many tasks.
5. Where an anchor has several contexts, each suffix shard of at most about ``suffix_bytes`` sorts its suffixes (Larsson-Sadakane), takes common prefixes (Kasai)
   and finds the smallest id of each window; sorted windows of several suffix shards of a task are merged by binary search.
6. Shards get the removed spans of their documents back and cut them out.

Defined results: null text is empty; null ids rank below all others; rows that repeat an id are one document, which
never removes from itself, and each keeps its own text and spans; cut characters leave no bytes of theirs in ``text`` of the
filter form; an empty table gives no rows; a text shorter than ``length`` bytes loses nothing; other columns are kept or ignored.
"""

from __future__ import annotations

import hashlib

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import lean
from .suffixes import common_prefixes, locate, merge_windows, suffix_array, window_words

LENGTH, GRAM = 50, 20
SEGMENT = 125_000  # bytes that are hashed at once: their arrays stay in a core's cache
_PLACE = np.uint64((1 << 24) - 1)
_TOP = np.uint64(32)
_BASE = 0x9E3779B97F4A7C15
_UNIT = np.random.default_rng(20_240_501).integers(1, 2**63, 256, dtype=np.uint64) * np.uint64(2) + np.uint64(1)
_POWERS: dict[str, np.ndarray] = {}


def _powers(n: int) -> tuple[np.ndarray, np.ndarray]:
    if len(_POWERS.get("up", ())) < n:
        inverse = pow(_BASE, -1, 2**64)
        for name, base in (("up", _BASE), ("down", inverse)):
            x = np.full(n, np.uint64(base))
            x[0] = 1
            _POWERS[name] = np.cumprod(x, dtype=np.uint64)
    return _POWERS["up"][:n], _POWERS["down"][:n]


def _mix(x: np.ndarray) -> np.ndarray:
    x = (x ^ (x >> np.uint64(32))) * np.uint64(0xD6E8FEB86659FD93)
    x = (x ^ (x >> np.uint64(32))) * np.uint64(0xD6E8FEB86659FD93)
    return x ^ (x >> np.uint64(32))


STEP = 4  # neighbouring windows of a hot anchor that are dealt together


def _split(a: np.ndarray, b: np.ndarray, p: np.ndarray, h: np.ndarray, hot: np.ndarray, digest, length: int, gram: int) -> tuple[np.ndarray, ...]:
    """(first window, last window, anchor, key): contexts of hot anchors cut by where the anchor lies in the window, keyed by the bytes that all windows of a cut share."""
    split = _among(h >> _TOP, hot)
    if not split.any():
        return a, b, p, h
    cuts = [(a[~split], b[~split], p[~split], h[~split])]
    a, b, p = a[split], b[split], p[split]
    for q in range(0, length - gram + 1, STEP):
        low, high = np.maximum(a, p - (q + STEP - 1)), np.minimum(b, p - q)
        ok = low <= high
        begin = p[ok] - q
        cuts.append((low[ok], high[ok], p[ok], _mix(digest(begin, begin - (STEP - 1) + length) ^ np.uint64((2 * q + 1) * 0x9E3779B9))))
    return tuple(np.concatenate(x) for x in zip(*cuts))


def _among(x: np.ndarray, ascending: np.ndarray) -> np.ndarray:
    if not len(ascending):
        return np.zeros(len(x), bool)
    return ascending[np.minimum(np.searchsorted(ascending, x), len(ascending) - 1)] == x


def contexts(texts: list[bytes], length: int = LENGTH, gram: int = GRAM, hot: np.ndarray = np.zeros(0, np.uint64)) -> tuple[np.ndarray, ...]:
    """(text, first window, last window, key, context hash) of all contexts of all texts.  The key is the anchor's hash, but for ``hot`` anchors."""
    found: list[tuple[np.ndarray, ...]] = []
    held: list[tuple[int, int, bytes]] = []
    size = 0

    def flush() -> None:
        raw = np.frombuffer(b"".join(x for _, _, x in held), np.uint8)
        n = len(raw)
        up, down = _powers(n + 1)
        total = np.concatenate([np.zeros(1, np.uint64), np.cumsum(_UNIT[raw] * down[:n], dtype=np.uint64)])
        grams = _mix((total[gram:] - total[:-gram]) * up[: n - gram + 1])
        low = (grams & ~_PLACE) | np.arange(len(grams), dtype=np.uint64)
        width, span = 1, length - gram + 1
        while 2 * width <= span:
            low = np.minimum(low[:-width], low[width:])
            width *= 2
        if width < span:
            low = np.minimum(low[: len(low) - (span - width)], low[span - width :])
        ends = np.cumsum([len(x) for _, _, x in held])
        begins = ends - [len(x) for _, _, x in held]
        valid = np.concatenate([np.arange(a, b - length + 1) for a, b in zip(begins.tolist(), ends.tolist())])
        anchor = (low[valid] & _PLACE).astype(np.int64)
        first = np.flatnonzero(np.concatenate([[True], anchor[1:] != anchor[:-1]]))
        last = np.append(first[1:], len(anchor)) - 1
        a, b, p = valid[first], valid[last], anchor[first]
        digest = lambda x, y: (total[y] - total[x]) * up[x]
        a, b, p, key = _split(a, b, p, grams[p], hot, digest, length, gram)
        c = _mix(digest(a, b + length) ^ ((b - a).astype(np.uint64) * np.uint64(0xA24BAED4963EE407)) ^ ((p - a).astype(np.uint64) * np.uint64(0x9FB21C651E98DF25)))
        which = np.searchsorted(ends, a, side="right")
        text = np.array([t for t, _, _ in held])[which]
        shift = np.array([o for _, o, _ in held])[which] - begins[which]
        found.append((text, a + shift, b + shift, key, c))

    for t, raw in enumerate(texts):
        for at in range(0, len(raw), SEGMENT):
            part = raw[at : at + SEGMENT + length - 1]  # windows that start in the next part are its own
            if len(part) >= length:
                held.append((t, at, part))
                size += len(part)
            if size >= SEGMENT:
                flush()
                held, size = [], 0
    if held:
        flush()
    if not found:
        none = np.zeros(0, np.int64)
        return none, none, none, none.astype(np.uint64), none.astype(np.uint64)
    return tuple(np.concatenate(x) for x in zip(*found))


def _merge_spans(doc: np.ndarray, a: np.ndarray, b: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Union of half-open spans of each document."""
    if not len(doc):
        return doc, a, b
    order = np.lexsort((a, doc))
    doc, a, b = doc[order], a[order], b[order]
    new_doc = np.concatenate([[True], doc[1:] != doc[:-1]])
    shift = np.cumsum(new_doc) * (int(b.max()) + 2)  # documents apart, so that one running maximum serves all
    reach = np.maximum.accumulate(b + shift)
    first = np.flatnonzero(np.concatenate([[True], (a + shift)[1:] > reach[:-1]]))
    last = np.append(first[1:], len(a)) - 1
    return doc[first], a[first], reach[last] - shift[first]


def _pack(*cols: np.ndarray) -> bytes:
    return b"".join(np.ascontiguousarray(c).tobytes() for c in cols)


ANCHOR = 4  # bytes of an anchor's hash by which anchors are told apart; its bucket comes from the others
_ANCHOR = np.dtype([("hash", "u1", ANCHOR), ("contexts", "<u2")])
MANY = 1 << 15  # added to ``contexts`` if the shard has the anchor in several documents
_SPAN = np.dtype([("row", "<u4"), ("a", "<u4"), ("b", "<u4")])


def _narrow(x: np.ndarray) -> np.ndarray:
    return x.astype("<u8").view(np.uint8).reshape(-1, 8)[:, :ANCHOR]


def _wide(x: np.ndarray) -> np.ndarray:
    out = np.zeros((len(x), 8), np.uint8)
    out[:, :ANCHOR] = x
    return out.view("<u8").ravel()


def _docs_of(table):
    """The shard's rows in order of id and text, their ids, and their texts as bytes: a row's number is the same in every step."""
    import pyarrow as pa
    import pyarrow.compute as pc

    ids = np.asarray(pc.fill_null(table.column("doc_id").cast(pa.int64()), -(2**63)))
    raw = table.column("text").cast(pa.binary()).fill_null(b"").to_pylist()
    order = np.argsort(ids, kind="stable")
    again = np.flatnonzero(ids[order][1:] == ids[order][:-1])
    if len(again):
        order = np.array(sorted(order.tolist(), key=lambda k: (ids[k], raw[k])), np.int64)
    if (order[1:] > order[:-1]).all():
        return table, ids, raw
    return table.take(pa.array(order)), ids[order], [raw[k] for k in order.tolist()]


def _by_bucket(bucket: np.ndarray):
    order = np.argsort(bucket, kind="stable")
    own, first = np.unique(bucket[order], return_index=True)
    return zip(own.tolist(), np.split(order, first[1:])) if len(own) else ()


def _rows(rows: list[tuple], *names: str):
    import pyarrow as pa

    cols = list(zip(*rows)) or [()] * len(names)
    return pa.table({n: pa.array(c, pa.binary() if n == "blob" else pa.int64()) for n, c in zip(names, cols)})


def _anchors(n_buckets: int, length: int, gram: int):
    """Shard -> (bucket, shard, blob): its anchors, how many contexts each has, and whether in several documents."""

    def run(key, table):
        _, ids, raw = _docs_of(table)
        t, _, _, h, c = contexts(raw, length, gram)
        doc = ids[t]
        order = np.lexsort((c, h))
        h, c, doc = h[order], c[order], doc[order]
        first = np.flatnonzero(np.concatenate([[True], h[1:] != h[:-1]])) if len(h) else np.zeros(0, np.int64)
        n = np.add.reduceat(np.concatenate([[1], (h[1:] != h[:-1]) | (c[1:] != c[:-1])]), first) if len(h) else first
        many = np.minimum.reduceat(doc, first) < np.maximum.reduceat(doc, first) if len(h) else first
        out = np.zeros(len(first), _ANCHOR)
        out["hash"], out["contexts"] = _narrow(h[first] >> _TOP), np.minimum(n, MANY - 1) + MANY * many
        return _rows([(b, key[0].as_py(), out[i].tobytes()) for b, i in _by_bucket(((h[first] & _PLACE) % np.uint64(n_buckets)).astype(np.int64))], "bucket", "shard", "blob")

    return run


def _candidates(hot_contexts: int):
    """Bucket -> (shard, blob): which of a shard's anchors several documents have, hot ones first."""

    def run(table):
        parts = [np.frombuffer(b, _ANCHOR) for b in table.column("blob").to_pylist()]
        shard = np.repeat(np.asarray(table.column("shard")), [len(x) for x in parts])
        every = np.concatenate(parts)
        own, at = np.unique(_wide(every["hash"]), return_inverse=True)
        held = every["contexts"].astype(np.int64)
        several = (np.bincount(at, minlength=len(own)) > 1) | (np.bincount(at, held >= MANY) > 0)
        hot = np.bincount(at, held % MANY) > hot_contexts
        keep = np.flatnonzero(several[at])
        rows = []
        for s, i in _by_bucket(shard[keep]):
            mine = at[keep[i]]
            is_hot = hot[mine]
            rows.append((s, np.int64(is_hot.sum()).tobytes() + _pack(_narrow(own[mine[is_hot]]), _narrow(own[mine[~is_hot]]))))
        return _rows(rows, "shard", "blob")

    return run


def collapse(raw: list[bytes], t: np.ndarray, a: np.ndarray, z: np.ndarray, c: np.ndarray) -> tuple[np.ndarray, list[bytes]]:
    """(number of each string raw[t][a:z], the strings), equal strings once: hashes ``c`` bring them together, their bytes decide."""
    group, bodies = np.zeros(len(t), np.int64), []
    odd: dict[bytes, int] = {}
    last = None
    order = np.argsort(c, kind="stable")
    for k, text, x, y, h in zip(order.tolist(), t[order].tolist(), a[order].tolist(), z[order].tolist(), c[order].tolist()):
        own = raw[text][x:y]
        if h != last:
            last, own_group = h, len(bodies)
            bodies.append(own)
            odd.clear()
        elif bodies[own_group] != own:  # two strings of one hash
            if own not in odd:
                odd[own] = len(bodies)
                bodies.append(own)
            group[k] = odd[own]
            continue
        group[k] = own_group
    return group, bodies


def _select(n_routes: int, length: int, gram: int):
    """Shard and its candidates -> (route, shard, blob): bytes of its contexts, equal ones once; spans already sure on route -1 - shard."""

    def run(key, docs, verdicts):
        import pyarrow as pa

        shard, rows = key[0].as_py(), []
        if docs.num_rows:
            _, ids, raw = _docs_of(docs)
            hot, cool = [np.zeros(0, np.uint64)], [np.zeros(0, np.uint64)]
            for blob in verdicts.column("blob").to_pylist():
                both = _wide(np.frombuffer(blob, np.uint8, offset=8).reshape(-1, ANCHOR))
                n = int(np.frombuffer(blob, "<i8", 1)[0])
                hot.append(both[:n])
                cool.append(both[n:])
            hot = np.unique(np.concatenate(hot))
            t, a, b, h, c = contexts(raw, length, gram)
            wanted = np.unique(np.concatenate([hot, *cool]))
            ask = _among(h >> _TOP, wanted)
            if len(hot):  # again, with contexts of hot anchors cut
                t, a, b, h, c, ask = _with_cuts(raw, length, gram, hot, (t, a, b, h, c), ask)
            t, a, b, h, c = t[ask], a[ask], b[ask], h[ask], c[ask]
            group, bodies = collapse(raw, t, a, b + length, c)
            doc = ids[t]
            least = np.full(len(bodies), np.iinfo(np.int64).max)
            np.minimum.at(least, group, doc)
            sure = doc > least[group]
            row, x, y = _merge_spans(t[sure], a[sure], b[sure] + length)
            if len(row):
                rows.append((-1 - shard, shard, _spans(row, x, y)))
            open_at = np.flatnonzero(~sure)
            open_at = open_at[np.argsort(group[open_at], kind="stable")]
            first = np.flatnonzero(np.concatenate([[True], np.diff(group[open_at]) > 0])) if len(open_at) else open_at
            count = np.diff(np.append(first, len(open_at)))
            key = h[open_at[first]]
            route = ((key & _PLACE) % np.uint64(n_routes)).astype(np.int64)
            by = np.argsort(route, kind="stable")
            first, count, key, route = first[by], count[by], key[by], route[by]
            # all columns in order of the routes: a route's part of each is one slice
            ends = np.concatenate([[0], np.cumsum(count)])
            at = open_at[np.repeat(first - ends[:-1], count) + np.arange(ends[-1])]
            place = np.zeros(len(at), _SPAN)
            place["row"], place["a"] = t[at], a[at]
            mine = group[open_at[first]]
            body = [bodies[g] for g in mine.tolist()]
            cols = [memoryview(np.ascontiguousarray(x)).cast("B") for x in (least[mine].astype("<i8"), np.array([len(x) for x in body], "<u2"), count.astype("<u4"), (key >> _TOP).astype("<u4"), place.view(np.uint8))] if len(mine) else []
            own, low = np.unique(route, return_index=True)
            low = np.append(low, len(route))
            codec = pa.Codec("zstd")
            for r, x, y, u, v in zip(own.tolist(), low[:-1].tolist(), low[1:].tolist(), ends[low[:-1]].tolist(), ends[low[1:]].tolist()):
                cut = [c[n * (u if n == _SPAN.itemsize else x) : n * (v if n == _SPAN.itemsize else y)] for c, n in zip(cols, (8, 2, 4, 4, _SPAN.itemsize))]
                rows.append((r, shard, b"".join([np.array([y - x, v - u], "<i8").tobytes(), *cut, codec.compress(b"".join(body[x:y]), asbytes=True)])))
        return _rows(rows, "route", "shard", "blob")

    return run


def _with_cuts(raw: list[bytes], length: int, gram: int, hot: np.ndarray, plain: tuple[np.ndarray, ...], ask: np.ndarray):
    """The contexts with those of hot anchors cut, and which of them are candidates: a cut one always is."""
    is_hot = _among(plain[3] >> _TOP, hot)
    text, begin, last = (x[is_hot] for x in plain[:3])
    # the bytes of a context have its anchor: they alone give its cuts
    own, a, b, h, c = contexts([raw[k][x:y] for k, x, y in zip(text.tolist(), begin.tolist(), (last + length).tolist())], length, gram, hot)
    keep = ask & ~is_hot
    cut = [np.concatenate([x[keep], y]) for x, y in zip(plain, (text[own], a + begin[own], b + begin[own], h, c))]
    return (*cut, np.ones(len(cut[0]), bool))


def _spans(row: np.ndarray, a: np.ndarray, b: np.ndarray) -> bytes:
    out = np.zeros(len(row), _SPAN)
    out["row"], out["a"], out["b"] = row, a, b
    return out.tobytes()


def smallest_ids(bodies: list[bytes], doc: np.ndarray, length: int, suffix_bytes: int) -> np.ndarray:
    """The smallest id that has the window at each start of each body, one body after another; by suffix arrays of at most about ``suffix_bytes`` each."""
    sizes = np.array([len(x) for x in bodies], np.int64)
    windows = np.maximum(sizes - length + 1, 0)
    begins = np.concatenate([[0], np.cumsum(windows)])
    out = np.full(int(begins[-1]), np.iinfo(np.int64).max)
    part = np.cumsum(sizes) // suffix_bytes
    shards, merged = [], []
    for p in np.unique(part).tolist():
        pick = np.flatnonzero(part == p)
        text = np.frombuffer(b"".join(bodies[k] for k in pick.tolist()), np.uint8)
        begin = np.cumsum(sizes[pick]) - sizes[pick]
        owner = np.repeat(np.arange(len(pick), dtype=np.int32), sizes[pick])
        sa = suffix_array(text)  # in full order: Kasai's bound needs it
        group = np.cumsum(common_prefixes(text, sa, length) < length) - 1
        room = (begin + sizes[pick])[owner[sa]] - sa >= length  # windows of one body only
        sa, group = sa[room], group[room]
        group = np.cumsum(np.concatenate([[True], group[1:] != group[:-1]])) - 1 if len(group) else group
        first = np.flatnonzero(np.concatenate([[True], group[1:] != group[:-1]])) if len(group) else group
        own = owner[sa]
        least = np.minimum.reduceat(doc[pick][own], first) if len(first) else np.zeros(0, np.int64)
        place = begins[pick][own] + (sa - begin[own])
        words = window_words(text, sa[first], length)
        shards.append((place, group, words))
        merged.append((words, least))
    while len(merged) > 1:  # two at a time
        merged = [merge_windows(*merged[k], *merged[k + 1]) if k + 1 < len(merged) else merged[k] for k in range(0, len(merged), 2)]
    for place, group, words in shards:
        out[place] = merged[0][1][group if len(shards) == 1 else locate(merged[0][0], words)[group]]
    return out


def _resolve(length: int, suffix_bytes: int):
    """Route -> (shard, blob) with removed spans."""

    def run(key, table):
        import pyarrow as pa

        if key[0].as_py() < 0:
            return table.select(["shard", "blob"])
        number: dict[bytes, int] = {}
        docs, shards, counts, keys, places, which = [], [], [], [], [], []
        for s, blob in zip(table.column("shard").to_pylist(), table.column("blob").to_pylist()):
            n, m = np.frombuffer(blob, "<i8", 2).tolist()
            docs.append(np.frombuffer(blob, "<i8", n, 16))
            size = np.frombuffer(blob, "<u2", n, 16 + 8 * n).astype(np.int64)
            counts.append(np.frombuffer(blob, "<u4", n, 16 + 10 * n).astype(np.int64))
            keys.append(np.frombuffer(blob, "<u4", n, 16 + 14 * n))
            places.append(np.frombuffer(blob, _SPAN, m, 16 + 18 * n))
            body = pa.decompress(blob[16 + 18 * n + _SPAN.itemsize * m :], int(size.sum()), "zstd", asbytes=True)
            which += [number.setdefault(body[e - z : e], len(number)) for e, z in zip(np.cumsum(size).tolist(), size.tolist())]
            shards.append(np.full(n, s, np.int64))
        doc, shard, count, place, which = np.concatenate(docs), np.concatenate(shards), np.concatenate(counts), np.concatenate(places), np.array(which)
        least = np.full(len(number), np.iinfo(np.int64).max)
        np.minimum.at(least, which, doc)
        # a string that is the only one of its key shares no window with another; the others are sorted
        bodies = list(number)
        windows = np.array([len(x) for x in bodies]) - length + 1
        begins = np.concatenate([[0], np.cumsum(windows)])
        key_of = np.zeros(len(bodies), np.uint32)
        key_of[which] = np.concatenate(keys)
        _, same, held = np.unique(key_of, return_inverse=True, return_counts=True)
        several = held[same] > 1
        lowest = np.repeat(least, windows)
        lowest[np.repeat(several, windows)] = smallest_ids([bodies[k] for k in np.flatnonzero(several).tolist()], least[several], length, suffix_bytes)
        # windows of every shard's contexts, one after another; runs of removed ones
        n_windows = np.diff(begins)[which]
        ask = np.repeat(np.arange(len(which)), n_windows)
        start = np.cumsum(n_windows) - n_windows
        at = np.arange(len(ask)) - start[ask]
        gone = np.flatnonzero(lowest[begins[which][ask] + at] < doc[ask])
        new = np.concatenate([[True], (np.diff(gone) > 1) | (np.diff(ask[gone]) > 0)]) if len(gone) else np.zeros(0, bool)
        first = np.flatnonzero(new)
        last = np.append(first[1:], len(gone)) - 1 if len(gone) else first
        of, low, high = ask[gone[first]], at[gone[first]], at[gone[last]] + length
        # each run at all places of its context
        begin = np.cumsum(count) - count
        run_of = np.repeat(np.arange(len(of)), count[of])
        spot = place[np.repeat(begin[of] - (np.cumsum(count[of]) - count[of]), count[of]) + np.arange(len(run_of))]
        a = spot["a"].astype(np.int64)
        row, x, y = _merge_spans((shard[of][run_of] << 32) | spot["row"].astype(np.int64), a + low[run_of], a + high[run_of])
        own, low = np.unique(row >> 32, return_index=True)
        every, low = memoryview(_spans(row & ((1 << 32) - 1), x, y)), np.append(low, len(row)) * _SPAN.itemsize
        return _rows([(k, bytes(every[i:j])) for k, i, j in zip(own.tolist(), low[:-1].tolist(), low[1:].tolist())], "shard", "blob")

    return run


def _spans_of(blobs: list[bytes]) -> dict[int, list[tuple[int, int]]]:
    """Removed spans of each row number."""
    every = np.frombuffer(b"".join(blobs), _SPAN)
    out: dict[int, list[tuple[int, int]]] = {}
    for r, x, y in zip(*(v.tolist() for v in _merge_spans(*(every[n].astype(np.int64) for n in ("row", "a", "b"))))):
        out.setdefault(r, []).append((x, y))
    return out


def _kept(raw: bytes, spans: list[tuple[int, int]]) -> bytes:
    out, at = [], 0
    for a, b in spans:
        out.append(raw[at:a])
        at = b
    return b"".join([*out, raw[at:]])


def _dealt(docs: DataFrame, shard_bytes: int) -> tuple[DataFrame, int]:
    total = docs.agg(F.sum(F.octet_length("text")).alias("b")).first()["b"] or 0
    n = max(1, -(-total // shard_bytes))
    return docs.withColumn("__shard", F.pmod(F.xxhash64(F.col("doc_id").cast("long")), F.lit(n))), n


def _removal(docs: DataFrame, finish, schema: str, length: int, gram: int, shard_bytes: int, suffix_bytes: int, hot_contexts: int) -> DataFrame:
    dealt, n = _dealt(docs, shard_bytes)
    n_buckets = max(4, n // 2)
    sent, told = "bucket long, shard long, blob binary", "shard long, blob binary"
    verdicts = dealt.groupBy("__shard").applyInArrow(lean(_anchors(n_buckets, length, gram)), sent).groupBy("bucket").applyInArrow(lean(_candidates(hot_contexts)), told)
    asked = dealt.groupBy("__shard").cogroup(verdicts.groupBy("shard")).applyInArrow(lean(_select(3 * n_buckets, length, gram)), "route long, shard long, blob binary")
    spans = asked.groupBy("route").applyInArrow(lean(_resolve(length, suffix_bytes)), told)
    return dealt.groupBy("__shard").cogroup(spans.groupBy("shard")).applyInArrow(lean(finish), schema)


#: Bytes of documents in a shard, bytes of a suffix array, and contexts from which an anchor is split over tasks.
SHARD_BYTES, SUFFIX_BYTES, HOT_CONTEXTS = 6_000_000, 1_500_000, 4_000


def repeated_passages(docs: DataFrame, *, length: int = LENGTH, gram: int = GRAM, shard_bytes: int = SHARD_BYTES, suffix_bytes: int = SUFFIX_BYTES, hot_contexts: int = HOT_CONTEXTS) -> DataFrame:
    """doc_id, n_bytes, n_removed, n_spans, kept_sha256."""

    def finish(docs, spans):
        import pyarrow as pa

        docs, _, raw = _docs_of(docs)
        by = _spans_of(spans.column("blob").to_pylist())
        rows = [(len(x), sum(b - a for a, b in own), len(own), hashlib.sha256(_kept(x, own)).hexdigest()) for x, own in ((x, by.get(k, [])) for k, x in enumerate(raw))]
        cols = list(zip(*rows)) or [(), (), (), ()]
        return pa.table({"doc_id": docs.column("doc_id"), "n_bytes": pa.array(cols[0], pa.int64()), "n_removed": pa.array(cols[1], pa.int64()), "n_spans": pa.array(cols[2], pa.int64()), "kept_sha256": pa.array(cols[3], pa.string())})

    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.coalesce("text", F.lit("")).alias("text"))
    return _removal(rows, finish, "doc_id long, n_bytes long, n_removed long, n_spans long, kept_sha256 string", length, gram, shard_bytes, suffix_bytes, hot_contexts)


def remove_passages(docs: DataFrame, *, length: int = LENGTH, gram: int = GRAM, shard_bytes: int = SHARD_BYTES, suffix_bytes: int = SUFFIX_BYTES, hot_contexts: int = HOT_CONTEXTS) -> DataFrame:
    """All rows and columns, with the removed bytes cut out of ``text`` (null stays null) and ``n_chars``, where present, counted anew."""
    columns = docs.columns

    def finish(docs, spans):
        import pyarrow as pa

        docs, _, raw = _docs_of(docs)
        by = _spans_of(spans.column("blob").to_pylist())
        null = docs.column("text").is_null().to_pylist()
        text = [None if gone else _kept(x, by[k]).decode(errors="ignore") if k in by else x.decode() for k, (x, gone) in enumerate(zip(raw, null))]
        new = {"text": pa.array(text, pa.string())}
        if "n_chars" in columns:
            n = docs.column("n_chars")
            new["n_chars"] = pa.array([len(t) if k in by else v for k, (t, v) in enumerate(zip(text, n.to_pylist()))], n.type)
        return pa.table({c: new.get(c, docs.column(c)) for c in columns})

    schema = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in docs.schema.fields)
    return _removal(docs, finish, schema, length, gram, shard_bytes, suffix_bytes, hot_contexts)
