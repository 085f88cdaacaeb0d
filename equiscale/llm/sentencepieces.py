"""Encoding and decoding with merge-type SentencePiece vocabularies.

A text is cut where a space follows a non-space: no piece of such a vocabulary
reaches over that place (checked when the model is loaded), so the units
between are independent and are encoded once per worker.  Units go through the
agenda of adjacent pairs ordered by score, then by place.  Every
text is compared with the sentencepiece library inside its Arrow batch (``check=False`` leaves that out); a difference raises.

Defined results: null and empty texts have begin and end ids only; texts of any length are encoded whole; repeated rows
are encoded each; an empty table gives no rows; any other columns of the input are ignored.
"""

from __future__ import annotations

import hashlib
import re
from functools import lru_cache

import numpy as np
from pyspark.sql import DataFrame

from .common import lean, text_chunks, texts
from .merges import PairTable, UnitCache, merge_words

MARK = "▁"


class PieceCodec:
    def __init__(self, model_file: str):
        import sentencepiece

        self.library = sp = sentencepiece.SentencePieceProcessor(model_file=model_file)
        self.size = n = sp.vocab_size()
        pieces = [sp.id_to_piece(i) for i in range(n)]
        plain = [not (sp.is_control(i) or sp.is_unknown(i) or sp.is_byte(i) or sp.is_unused(i)) for i in range(n)]
        if any(MARK in p.lstrip(MARK) for p, ok in zip(pieces, plain) if ok):
            raise ValueError("a piece holds a space after other characters; units are not independent")
        self.bytes_at = [sp.piece_to_id(f"<0x{b:02X}>") for b in range(256)]
        symbol = {p: i for i, p in enumerate(pieces) if plain[i]}
        self.extra: list[str] = []
        for p in list(symbol):
            for c in p:
                if c not in symbol:
                    symbol[c] = n + len(self.extra)
                    self.extra.append(c)
        order = {s: k for k, s in enumerate(sorted({sp.get_score(i) for i in range(n) if plain[i]}, reverse=True))}
        rows = [(symbol[p[:k]], symbol[p[k:]], order[sp.get_score(i)], i) for i, p in enumerate(pieces) if plain[i] and len(p) > 1 for k in range(1, len(p)) if p[:k] in symbol and p[k:] in symbol]
        self.table = PairTable(*map(list, zip(*rows)))
        self.symbol_of = np.arange(0x110000, dtype=np.int64) + n + len(self.extra)  # characters of no piece come after all symbols
        for c, i in symbol.items():
            if len(c) == 1:
                self.symbol_of[ord(c)] = i
        self.unit_cache = UnitCache(self._encode_units)
        raw = [b"" if sp.is_control(i) else " ⁇ ".encode() if sp.is_unknown(i) else bytes([int(p[3:5], 16)]) if sp.is_byte(i) else p.replace(MARK, " ").encode() for i, p in enumerate(pieces)]
        self._raw = np.frombuffer(b"".join(raw), np.uint8)
        self._raw_len = np.array([len(x) for x in raw], np.int64)
        self._raw_start = np.cumsum(self._raw_len) - self._raw_len
        self._text_bytes = [i for i in range(n) if sp.is_byte(i)]

    def _encode_units(self, units: list[str]) -> tuple[np.ndarray, np.ndarray]:
        """Units lack their first mark."""
        code = np.frombuffer("".join([MARK + u for u in units]).replace(" ", MARK).encode("utf-32-le"), np.uint32)
        flat, lens = merge_words(self.symbol_of[code], np.fromiter(map(len, units), np.int64, len(units)) + 1, self.table)
        if (flat >= self.size).any():
            base = self.size + len(self.extra)
            fallback = {s: [self.bytes_at[b] for b in (self.extra[s - self.size] if s < base else chr(s - base)).encode()] for s in np.unique(flat[flat >= self.size]).tolist()}
            grown = np.ones(len(flat), np.int64)
            odd = np.flatnonzero(flat >= self.size)
            grown[odd] = [len(fallback[s]) for s in flat[odd].tolist()]
            out = np.repeat(flat, grown)
            begin = np.cumsum(grown) - grown
            for i in odd.tolist():
                out[begin[i] : begin[i] + grown[i]] = fallback[int(flat[i])]
            word_of = np.repeat(np.arange(len(units)), lens)
            flat, lens = out, np.bincount(word_of, grown, len(units)).astype(np.int64)
        return flat, lens

    @staticmethod
    def units(text: str) -> list[str]:
        if not text:
            return []
        text = text.replace(MARK, " ")
        if "  " not in text and text[0] != " " and text[-1] != " ":
            return text.split(" ")
        return [u[1:] for u in re.findall(r" +[^ ]*", " " + text)]

    def encode(self, batch: list[str]) -> list[np.ndarray]:
        """Ids of each text, without begin and end ids."""
        split = [self.units(t) for t in batch]
        flat, lens = self.unit_cache.ids([u for s in split for u in s])
        ends = np.concatenate([[0], np.cumsum(lens)])[np.cumsum([0] + [len(s) for s in split])]
        return [flat[a:b] for a, b in zip(ends[:-1].tolist(), ends[1:].tolist())]

    def decode(self, ids: np.ndarray) -> str:
        ids = np.asarray(ids, np.int64)
        lens = self._raw_len[ids]
        raw = self._raw[np.repeat(self._raw_start[ids] - (np.cumsum(lens) - lens), lens) + np.arange(int(lens.sum()))].tobytes()
        shown = np.flatnonzero(lens)
        if len(shown) and raw[:1] == b" " and ids[shown[0]] not in self._text_bytes and not self.library.is_unknown(int(ids[shown[0]])):
            raw = raw[1:]
        try:
            return raw.decode()
        except UnicodeDecodeError:  # ids that no text encodes to
            return self.library.decode([int(i) for i in ids])


@lru_cache(maxsize=2)
def codec(model_file: str) -> PieceCodec:
    return PieceCodec(model_file)


def encode_documents(docs: DataFrame, model_file: str, *, check: bool = True) -> DataFrame:
    """doc_id, ids (array), decoded text: the operator's real output."""
    return _run(docs, model_file, check, False, "doc_id long, ids array<int>, decoded string")


def encode_digests(docs: DataFrame, model_file: str, *, check: bool = True) -> DataFrame:
    """doc_id, n_tokens and digests of ids and decoded text; ``checked``: compared with the library."""
    return _run(docs, model_file, check, True, "doc_id long, n_tokens long, ids_sha256 string, decoded_sha256 string, checked boolean")


def _run(docs: DataFrame, model_file: str, check: bool, digest: bool, schema: str) -> DataFrame:
    def run(batches):
        import pyarrow as pa

        pieces = codec(model_file)
        begin, end = pieces.library.bos_id(), pieces.library.eos_id()
        for batch in batches:
            for part in text_chunks(batch):
                ids_of, text_of = part.column(0), part.column(1).to_pylist()
                encoded = pieces.encode(text_of)
                decoded = [pieces.decode(x) for x in encoded]
                if check:
                    wanted = pieces.library.encode(text_of)
                    for text, ids, back, want, shown in zip(text_of, encoded, decoded, wanted, pieces.library.decode(wanted)):
                        if want != ids.tolist() or shown != back:
                            raise ValueError(f"encoding differs from the library's for {text[:80]!r}")
                if digest:
                    full = [np.concatenate([[begin], x, [end]]).astype("<u4") for x in encoded]
                    cols = [ids_of, pa.array([len(x) for x in full], pa.int64()), pa.array([hashlib.sha256(x.tobytes()).hexdigest() for x in full]), pa.array([hashlib.sha256(t.encode()).hexdigest() for t in decoded]), pa.array([check] * len(encoded))]
                    yield pa.RecordBatch.from_arrays(cols, ["doc_id", "n_tokens", "ids_sha256", "decoded_sha256", "checked"])
                else:
                    yield pa.RecordBatch.from_arrays([ids_of, pa.array([np.concatenate([[begin], x, [end]]).astype(np.int32) for x in encoded], pa.list_(pa.int32())), pa.array(decoded, pa.string())], ["doc_id", "ids", "decoded"])

    return texts(docs).mapInArrow(lean(run), schema)
