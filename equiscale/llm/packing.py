"""Packing token sequences by a grouping genetic algorithm on islands.

Documents are tokenised once; what is packed are thin rows (id, piece, length).
Pieces of full length fill a sequence alone.  The rest is dealt into blocks of
about ``block`` pieces and each block is packed by best fit.  Well-filled bins
stay; what lies in the other bins goes on to a next level with fewer blocks,
so that the remainders of all blocks meet.  On every level, however many blocks it has, blocks evolve on several islands (one Spark task
each), whose best packings migrate to the next island after each epoch.  A
chromosome is a list of bins (groups); crossover injects whole well-filled bins
of one parent into the other, removes the bins that hold the same documents
and puts the displaced ones back by best fit.  Work per task is bounded by the block size.
A block whose best fit meets the bound of total length is packed as well as can be, so evolution ends there at once; it works where
best fit misses the bound (``evolution`` reports bound, best fit and gain of each block).

Defined results: null and empty texts have the end id only; a text of more than
``capacity`` ids is cut into full pieces and a rest; repeated rows are packed each;
an empty table gives no rows; other columns of the input are ignored.
"""

from __future__ import annotations

import math
import random
import re
import zlib
from bisect import bisect_right, insort
from functools import lru_cache

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import cut, lean, release, text_chunks, texts
from .merges import PairTable, UnitCache, merge_words

PIECE_SCHEMA = "doc_id long, piece int, start long, length long, ids_crc32 long"


class WordCodec:
    """A word-level tokenizer file with end-of-word merges.  Chunks between blanks, and the words that they share, are encoded once per worker.

    Chunks of ASCII and Latin-1 letters go through the agenda of merges; a chunk with any other character goes to the tokenizers library.
    """

    def __init__(self, path: str):
        import json

        from tokenizers import Tokenizer

        self.library = Tokenizer.from_file(path)
        model = json.loads(open(path, encoding="utf-8").read())["model"]
        vocab = model["vocab"]
        merges = [m.split(" ") if isinstance(m, str) else m for m in model["merges"]]
        self.table = PairTable([vocab[a] for a, _ in merges], [vocab[b] for _, b in merges], range(len(merges)), [vocab[a + b] for a, b in merges])
        shown = _byte_characters()
        self.first = np.array([vocab[shown[b]] for b in range(256)], np.int64)
        self.last = np.array([vocab[shown[b] + model["end_of_word_suffix"]] for b in range(256)], np.int64)
        self.plain = re.compile("[ !-~À-ÖØ-öø-ÿ]*").fullmatch
        letters = "a-zªµºß-öø-ÿ"
        self.words = re.compile(f"'s|'t|'re|'ve|'m|'ll|'d|[{letters}]+|[0-9]| |[^ {letters}0-9]+").findall
        self.cache, self.word_cache = UnitCache(self._encode_chunks), UnitCache(self._encode_words, 300_000)

    def _encode_words(self, words: list[str]) -> tuple[np.ndarray, np.ndarray]:
        import pyarrow as pa
        import pyarrow.compute as pc

        size = pc.binary_length(pa.array(words, pa.string())).to_numpy().astype(np.int64)
        code = np.frombuffer("".join(words).encode(), np.uint8)
        symbols = self.first[code]
        ends = np.cumsum(size) - 1
        symbols[ends] = self.last[code[ends]]
        return merge_words(symbols, size, self.table)

    def _encode_chunks(self, chunks: list[str]) -> tuple[np.ndarray, np.ndarray]:
        line, odd = " ".join(chunks), {}
        if "<|" in line or not self.plain(line):
            odd = {k: self.library.encode(c, add_special_tokens=False).ids for k, c in enumerate(chunks) if "<|" in c or not self.plain(c)}
            line = " ".join("" if k in odd else c for k, c in enumerate(chunks))
        parts = self.words(line.lower())  # a blank ends each chunk but the last
        gap = np.fromiter(map(" ".__eq__, parts), bool, len(parts))
        flat, lens = self.word_cache.ids([w for w in parts if w != " "])
        per = np.bincount(np.cumsum(gap)[~gap], lens, len(chunks)).astype(np.int64)
        if odd:
            out, at, begin = [], 0, np.concatenate([[0], np.cumsum(per)])
            for k in sorted(odd):
                out += [flat[at : begin[k]], np.array(odd[k], np.int64)]
                at = begin[k]
                per[k] = len(odd[k])
            flat = np.concatenate([*out, flat[at:]])
        return flat, per

    def encode(self, batch) -> list[np.ndarray]:
        """Ids of each text of a list or an Arrow column.  Arrow splits at blanks and numbers the distinct chunks; only these are looked up."""
        import pyarrow as pa
        import pyarrow.compute as pc

        column = batch if isinstance(batch, pa.Array) else pa.array(batch, pa.string())
        split = pc.split_pattern(pc.replace_substring(column, "\n", " "), " ")
        chunks = pc.dictionary_encode(split.flatten())
        flat, lens = self.cache.ids(chunks.dictionary.to_pylist(), chunks.indices.to_numpy())
        ends = np.concatenate([[0], np.cumsum(lens)])[np.concatenate([[0], np.cumsum(split.value_lengths().to_numpy())])]
        return [flat[a:b] for a, b in zip(ends[:-1].tolist(), ends[1:].tolist())]


def _byte_characters() -> list[str]:
    """The printable character that stands for each byte in byte-level vocabularies."""
    own = [*range(33, 127), *range(161, 173), *range(174, 256)]
    rest = iter(range(256, 512))
    return [chr(b) if b in own else chr(next(rest)) for b in range(256)]


@lru_cache(maxsize=2)
def word_codec(path: str) -> WordCodec:
    return WordCodec(path)


def token_pieces(docs: DataFrame, tokenizer: str, *, capacity: int = 4096, end_id: int = 1) -> DataFrame:
    """One thin row for each piece of each document."""

    def run(batches):
        import pyarrow as pa

        codec = word_codec(tokenizer)
        for batch in batches:
            for part in text_chunks(batch, 4_000_000):
                ids_of, cols = part.column(0).to_pylist(), ([], [], [], [], [])
                for doc, ids in zip(ids_of, codec.encode(part.column(1))):
                    ids = np.append(ids, end_id).astype("<u4")
                    for k, at in enumerate(range(0, len(ids), capacity)):
                        own = ids[at : at + capacity]
                        for col, v in zip(cols, (doc, k, at, len(own), zlib.crc32(own.tobytes()))):
                            col.append(v)
                yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(cols, (pa.int64(), pa.int32(), pa.int64(), pa.int64(), pa.int64()))], ["doc_id", "piece", "start", "length", "ids_crc32"])

    return texts(docs).mapInArrow(lean(run), PIECE_SCHEMA)


class Bins:
    """Open bins by their room; the fullest bin that still takes a piece is found in one step."""

    def __init__(self, capacity: int):
        self.capacity, self.rooms, self.mask = capacity, {}, 0
        self.bins: list[list[int]] = []

    def add(self, items: list[int], used: int) -> None:
        self.bins.append(items)
        self._open(len(self.bins) - 1, self.capacity - used)

    def _open(self, b: int, room: int) -> None:
        if room > 0:
            self.rooms.setdefault(room, []).append(b)
            self.mask |= 1 << room

    def put(self, item: int, size: int) -> None:
        fits = self.mask >> size
        if not fits:
            self.add([item], size)
            return
        room = size + (fits & -fits).bit_length() - 1
        stack = self.rooms[room]
        b = stack.pop()
        if not stack:
            self.mask &= ~(1 << room)
        self.bins[b].append(item)
        self._open(b, room - size)


def load(items: list[int], sizes: list[int]) -> int:
    return sum(map(sizes.__getitem__, items))


def best_fit(sizes: list[int], capacity: int, items=None, bins: list[list[int]] | None = None, noise: random.Random | None = None) -> list[list[int]]:
    """Best fit of ``items`` (largest first; with ``noise``, about so) into ``bins`` and new ones."""
    open_bins = Bins(capacity)
    for b in bins or ():
        open_bins.add(b, load(b, sizes))
    key = (lambda i: -sizes[i] * noise.uniform(0.8, 1.0)) if noise else (lambda i: -sizes[i])
    for i in sorted(range(len(sizes)) if items is None else items, key=key):
        open_bins.put(i, sizes[i])
    return open_bins.bins


def fitness(bins: list[list[int]], sizes: list[int], capacity: int) -> float:
    return sum((load(b, sizes) / capacity) ** 2 for b in bins) / max(1, len(bins))


def swap_in(bins: list[list[int]], displaced: list[int], sizes: list[int], capacity: int) -> list[int]:
    """Trades a piece of a bin for a larger displaced one that still fits, bin by bin; returns what is displaced then, smaller than before and easier to place."""
    ranked = sorted((sizes[i], i) for i in displaced)
    for x in bins:
        room = capacity - load(x, sizes)
        if not room:
            continue
        best = (0, 0, 0)
        for k, i in enumerate(x):
            at = bisect_right(ranked, (sizes[i] + room, len(sizes))) - 1
            if at >= 0 and ranked[at][0] - sizes[i] > best[0]:
                best = (ranked[at][0] - sizes[i], k, at)
        if best[0]:
            _, k, at = best
            out = x[k]
            x[k] = ranked.pop(at)[1]
            insort(ranked, (sizes[out], out))
    return [i for _, i in ranked]


def crossover(a: list[list[int]], b: list[list[int]], sizes: list[int], capacity: int, rng: random.Random) -> list[list[int]]:
    """Whole well-filled bins of ``b`` go into ``a``; bins of ``a`` that hold one of their pieces go, and their other pieces are put back."""
    ranked = sorted(b, key=lambda x: -load(x, sizes))
    give = [list(x) for x in ranked[: max(1, len(ranked) // 2)] if rng.random() < 0.5]
    taken = {i for x in give for i in x}
    keep, displaced = [], []
    for x in a:
        if taken.isdisjoint(x):
            keep.append(list(x))
        else:
            displaced += [i for i in x if i not in taken]
    displaced = swap_in(keep, displaced, sizes, capacity)
    return best_fit(sizes, capacity, displaced, keep + give)


def mutate(bins: list[list[int]], sizes: list[int], capacity: int, rng: random.Random) -> list[list[int]]:
    """The emptiest bins and a few others are opened, their pieces traded for smaller ones where that fills a bin, and the rest put back in a noisy order."""
    ranked = sorted((list(b) for b in bins), key=lambda x: load(x, sizes))
    n = max(1, len(ranked) // 20)
    out, rest = ranked[:n], ranked[n:]
    rng.shuffle(rest)
    out, rest = out + rest[:n], rest[n:]
    return best_fit(sizes, capacity, swap_in(rest, [i for b in out for i in b], sizes, capacity), rest, rng)


def evolve(sizes: list[int], capacity: int, population: list[list[list[int]]], seed: int, *, members: int = 10, generations: int = 80, patience: int = 20) -> tuple[list[list[int]], int]:
    """(the best packing, generations that it took), from the ``population``, or from best fit if that is empty.  Ends at once when the bound of total length is met, which no packing can beat, and after ``patience`` generations without gain."""
    rng = random.Random(seed)
    bound = math.ceil(sum(sizes) / capacity)
    people = list(population) or [best_fit(sizes, capacity)]
    if min(map(len, people)) > bound:
        people += [best_fit(sizes, capacity, noise=rng) for _ in range(max(0, members - len(people)))]
    rank = lambda x: (x[0], -x[1])
    scored = sorted(((len(x), fitness(x, sizes, capacity), x) for x in people), key=rank)
    done = idle = 0
    while scored[0][0] > bound and done < generations and idle < patience:
        before = rank(scored[0])
        a, b = rng.sample(scored[: max(2, len(scored) // 2)], 2)
        for child in (crossover(a[2], b[2], sizes, capacity, rng), mutate(scored[0][2], sizes, capacity, rng)):
            own = (len(child), fitness(child, sizes, capacity), child)
            if rank(own) < rank(scored[-1]) and all(rank(own) != rank(x) for x in scored):
                scored[-1] = own
                scored.sort(key=rank)
        done += 1
        idle = 0 if rank(scored[0]) < before else idle + 1
    return scored[0][2], done


def _genome(bins: list[list[int]], n: int) -> bytes:
    out = np.zeros(n, "<i4")
    for b, items in enumerate(bins):
        out[items] = b
    return out.tobytes()


def _bins(genome: bytes) -> list[list[int]]:
    own = np.frombuffer(genome, "<i4")
    order = np.argsort(own, kind="stable")
    return [x.tolist() for x in np.split(order, np.flatnonzero(np.diff(own[order])) + 1)] if len(own) else []


BLOCK = "block long, n_bins long, fit double, open boolean, own binary, data binary"


def _blocks(items: DataFrame, n_blocks: int, capacity: int) -> DataFrame:
    """The pieces of each block as one Arrow stream, their number is about n / n_blocks; with its best fit, and whether that misses the bound of total length."""

    def gather(table):
        import pyarrow as pa

        table = table.sort_by([("doc_id", "ascending"), ("piece", "ascending"), ("__row", "ascending")])
        sink = pa.BufferOutputStream()
        with pa.ipc.new_stream(sink, table.schema) as out:
            out.write_table(table)
        sizes = table.column("length").to_pylist()
        bins = best_fit(sizes, capacity)
        row = {"block": table.column("__block")[0].as_py(), "n_bins": len(bins), "fit": fitness(bins, sizes, capacity), "open": len(bins) > math.ceil(sum(sizes) / capacity), "own": _genome(bins, len(sizes)), "data": sink.getvalue().to_pybytes()}
        return pa.Table.from_pylist([row], pa.schema([("block", pa.int64()), ("n_bins", pa.int64()), ("fit", pa.float64()), ("open", pa.bool_()), ("own", pa.binary()), ("data", pa.binary())]))

    return items.withColumn("__row", F.monotonically_increasing_id()).withColumn("__block", F.pmod(F.xxhash64("__row"), F.lit(n_blocks))).groupBy("__block").applyInArrow(lean(gather), BLOCK)


def _read(data: bytes):
    import pyarrow as pa

    return pa.ipc.open_stream(data).read_all()


STATE = "block long, island int, n_bins long, fit double, generations long, own binary, data binary"


def _epoch(state: DataFrame, capacity: int, seed: int) -> DataFrame:
    """Each island of each block evolves from its own best and the one that came from its neighbour."""

    def run(batches):
        import pyarrow as pa

        for batch in batches:
            for r in batch.to_pylist():
                sizes = _read(r["data"]).column("length").to_pylist()
                best, used = evolve(sizes, capacity, [_bins(g) for g in (r["own"], r["guest"]) if g is not None], seed + 1000 * r["island"] + r["block"])
                row = {"block": r["block"], "island": r["island"], "n_bins": len(best), "fit": fitness(best, sizes, capacity), "generations": (r["generations"] or 0) + used, "own": _genome(best, len(sizes)), "data": r["data"]}
                yield pa.RecordBatch.from_pylist([row], pa.schema([("block", pa.int64()), ("island", pa.int32()), ("n_bins", pa.int64()), ("fit", pa.float64()), ("generations", pa.int64()), ("own", pa.binary()), ("data", pa.binary())]))

    return state.mapInArrow(lean(run), STATE)


def _settled(blocks: DataFrame) -> DataFrame:
    return blocks.select("block", F.lit(0).alias("island"), "n_bins", "fit", F.lit(0).cast("long").alias("generations"), "own", "data")


def _evolved(blocks: DataFrame, capacity: int, islands: int, epochs: int, seed: int) -> DataFrame:
    """All written blocks: those whose best fit cannot be beaten as they are, the islands of the others after all epochs; after each, every island's best goes to the next island as a guest."""
    settled, todo = _settled(blocks.filter("not open")), blocks.filter("open")
    n_open = todo.count()
    if not n_open:
        return settled
    state = todo.select("block", "data", F.explode(F.sequence(F.lit(0), F.lit(islands - 1))).alias("island"), F.lit(None).cast("long").alias("generations"), "own", F.lit(None).cast("binary").alias("guest"))
    tasks = max(1, min(n_open * islands, 4 * blocks.sparkSession.sparkContext.defaultParallelism))
    done = None
    for epoch in range(epochs):
        last, done = done, cut(_epoch(state.repartition(tasks, "block", "island"), capacity, seed + 7919 * epoch))
        if last is not None:
            release(last)
        guest = done.select("block", F.pmod(F.col("island") + 1, F.lit(islands)).cast("int").alias("island"), F.col("own").alias("guest"))
        state = done.join(guest, ["block", "island"])
    return settled.unionByName(done)


def evolution(pieces: DataFrame, *, capacity: int = 4096, block: int = 4000, islands: int = 4, epochs: int = 2, seed: int = 11) -> DataFrame:
    """What evolution gains on the pieces shorter than ``capacity``: block, pieces, bound (of total length), best_fit (bins of best fit alone), evolved (bins of the best island), generations (of all islands)."""
    rest = cut(pieces.filter(F.col("length") < capacity))
    n_blocks = max(1, -(-rest.count() // block))
    blocks = cut(_blocks(rest, n_blocks, capacity))
    done = _evolved(blocks, capacity, islands, epochs, seed).groupBy("block").agg(F.min("n_bins").alias("evolved"), F.sum("generations").alias("generations"))

    def bounds(batches):
        import pyarrow as pa

        for batch in batches:
            for r in batch.to_pylist():
                sizes = _read(r["data"]).column("length").to_pylist()
                yield pa.RecordBatch.from_arrays([pa.array([v], pa.int64()) for v in (r["block"], len(sizes), math.ceil(sum(sizes) / capacity), r["n_bins"])], ["block", "pieces", "bound", "best_fit"])

    return blocks.select("block", "n_bins", "data").mapInArrow(lean(bounds), "block long, pieces long, bound long, best_fit long").join(done, "block")


def _pack_level(items: DataFrame, n_blocks: int, capacity: int, islands: int, epochs: int, seed: int, level: int, keep_above: float) -> DataFrame:
    """Rows of ``items`` with sequence_id, offset and ``stays`` (its bin is filled to ``keep_above`` at least).  Blocks whose best fit misses the bound evolve, on every level alike."""
    blocks = cut(_blocks(items, n_blocks, capacity))
    done = _evolved(blocks, capacity, islands, epochs, seed)
    best = done.groupBy("block").agg(F.max_by(F.struct("own", "data"), F.struct(-F.col("n_bins"), F.col("fit"), -F.col("island"))).alias("best")).select("block", "best.own", "best.data")

    def unfold(batches):
        import pyarrow as pa

        for batch in batches:
            for r in batch.to_pylist():
                table, own = _read(r["data"]), np.frombuffer(r["own"], "<i4").astype(np.int64)
                size = table.column("length").to_numpy()
                used = np.bincount(own, size) if len(own) else np.zeros(0)
                order = np.lexsort((np.arange(len(own)), own))
                run = np.cumsum(size[order]) - size[order]
                first = np.concatenate([[True], np.diff(own[order]) > 0]) if len(own) else np.zeros(0, bool)
                offset = np.zeros(len(own), np.int64)
                offset[order] = run - np.maximum.accumulate(np.where(first, run, 0))
                table = table.drop_columns([c for c in table.column_names if c.startswith("__")])
                table = table.append_column("sequence_id", pa.array((((level << 36) | r["block"]) << 20) | own)).append_column("offset", pa.array(offset)).append_column("stays", pa.array(used[own] >= keep_above * capacity))
                yield from table.to_batches()

    return best.mapInArrow(lean(unfold), PIECE_SCHEMA + ", sequence_id long, offset long, stays boolean")


def pack(pieces: DataFrame, *, capacity: int = 4096, block: int = 4000, islands: int = 4, epochs: int = 2, levels: int = 4, keep_above: float = 0.98, seed: int = 11) -> DataFrame:
    """Adds sequence_id and offset to every piece row."""
    pieces = cut(pieces)
    full = pieces.filter(F.col("length") >= capacity).withColumns({"sequence_id": F.monotonically_increasing_id().bitwiseOR(F.lit(1 << 61)), "offset": F.lit(0).cast("long")})
    rest, out = pieces.filter(F.col("length") < capacity), full
    for level in range(levels):
        n = rest.count()
        if not n:
            break
        n_blocks = -(-n // block)
        last = n_blocks == 1 or level == levels - 1
        packed = cut(_pack_level(rest, n_blocks, capacity, islands, epochs, seed + level, level, keep_above))
        out = out.unionByName((packed if last else packed.filter("stays")).drop("stays"))
        if last:
            break
        rest = packed.filter("not stays").drop("stays", "sequence_id", "offset")
    return out


def pack_documents(docs: DataFrame, tokenizer: str, *, capacity: int = 4096, end_id: int = 1, **options) -> DataFrame:
    return pack(token_pieces(docs, tokenizer, capacity=capacity, end_id=end_id), capacity=capacity, **options)
