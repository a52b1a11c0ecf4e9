"""BPE encoding and decoding with forced boundaries.

A byte pair that occurs inside no vocabulary token marks a certain cut: no merge can cross it. Texts
are cut at all such pairs (outside white space, before no apostrophe and between characters only, where
pre-tokenisation cannot see across the cut either), equal fragments of a chunk are encoded once each
and independently, and the ids of a text are its fragments' ids in order. The result is that of the
tokenizers library on the whole text. Special token strings are found first, as the library does.

Nulls and odd input: a null text is empty; empty texts have no ids; very long texts are cut like
others (a chunk holds one text at least); repeated rows, clashing extra columns and an empty table
need nothing special, the operator being a scalar function of the text.
"""

from __future__ import annotations

import hashlib
import json
from functools import lru_cache

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import regex
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import ArrayType, IntegerType, LongType, StringType, StructField, StructType

from meshprofile.llm.common import bounded_batches, flat_bytes, table, text_chunks

MODEL = "byte_bpe_50k.json"
CACHE = 50_000
#: The pre-tokenisation pattern of byte-level BPE files that use the library's own.
SPLIT = r"'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+"


def model_path(name: str = MODEL) -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


def byte_letters() -> dict[str, int]:
    """The printable letter that stands for each byte in byte-level vocabularies."""
    plain = [b for b in range(256) if 33 <= b <= 126 or 161 <= b <= 172 or b >= 174]
    rest = [b for b in range(256) if b not in set(plain)]
    return {chr(b): b for b in plain} | {chr(256 + i): b for i, b in enumerate(rest)}


class ForcedBoundaryBPE:
    """Encoder and decoder of one byte-level BPE file."""

    def __init__(self, path: str):
        import tiktoken

        with open(path, encoding="utf-8") as f:
            spec = json.load(f)
        letters = byte_letters()
        vocab = spec["model"]["vocab"]
        self.special = {t["content"]: t["id"] for t in spec.get("added_tokens", []) if t["special"]}
        ranks = {bytes(letters[c] for c in k): i for k, i in vocab.items() if k not in self.special}
        self.size = max(max(vocab.values()), *self.special.values(), 0) + 1
        self.bytes_of = [b""] * self.size
        for k, i in [*ranks.items(), *((k.encode(), i) for k, i in self.special.items())]:
            self.bytes_of[i] = k
        self.text_of = [str(i).encode() for i in range(self.size)]
        # ids grow with merge order, so they serve as ranks
        self.piece = tiktoken.Encoding("bytes", pat_str=SPLIT, mergeable_ranks=ranks, special_tokens={})
        inside = np.zeros((256, 256), bool)
        for k in ranks:
            for a, b in zip(k, k[1:]):
                inside[a, b] = True
        cut = ~inside
        cut[[*b" \t\n\r\x0b\x0c\x1c\x1d\x1e\x1f"]] = False
        cut[:, 0x27] = False
        cut[:, 0x80:0xC0] = False
        self.cut = cut.ravel()
        self.known: dict[bytes, tuple[int, ...]] = {}
        self.most_known = CACHE
        self.specials = regex.compile("|".join(map(regex.escape, sorted(self.special, key=len, reverse=True)))) if self.special else None

    def fragments(self, raw: np.ndarray, offsets: np.ndarray) -> np.ndarray:
        """Starts of the fragments of texts that lie end to end in raw; each text begins one."""
        if not len(raw):
            return np.zeros(0, np.int64)
        pair = raw[:-1].astype(np.uint16) * np.uint16(256) + raw[1:]
        at = np.flatnonzero(self.cut[pair])
        # a Unicode space may end in any of these bytes: keep it and what follows together
        prev = raw[np.maximum(at - 1, 0)]
        space = (raw[at] >= 0x80) & np.isin(prev, (0xC2, 0x9A, 0x80, 0x81))
        starts = np.zeros(len(raw) + 1, bool)
        starts[at[~space] + 1] = True
        starts[offsets[:-1]] = True
        return np.flatnonzero(starts[: len(raw)])

    def _ids(self, piece: bytes) -> tuple[int, ...]:
        got = self.known.get(piece)
        if got is None:
            got = tuple(self.piece.encode_ordinary(piece.decode()))
            if len(self.known) >= self.most_known:
                self.known.clear()
            if len(piece) <= 64:
                self.known[piece] = got
        return got

    def _plain(self, texts: pa.Array) -> tuple[np.ndarray, np.ndarray]:
        raw, offsets = flat_bytes(texts)
        starts = self.fragments(raw, offsets)
        if not len(starts):
            return np.zeros(0, np.int32), np.zeros(len(texts) + 1, np.int64)
        ends = np.r_[starts, len(raw)]
        whole = pa.Array.from_buffers(pa.large_binary(), len(starts), [None, pa.py_buffer(ends.astype(np.int64)), pa.py_buffer(raw)])
        coded = whole.dictionary_encode()
        each = [self._ids(p) for p in coded.dictionary.to_pylist()]
        n = np.fromiter(map(len, each), np.int64, len(each))
        flat = np.fromiter((i for x in each for i in x), np.int32, int(n.sum()))
        begin = np.cumsum(n) - n
        code = coded.indices.to_numpy()
        size = n[code]
        upto = np.r_[0, np.cumsum(size)]
        ids = flat[np.repeat(begin[code] - upto[:-1], size) + np.arange(upto[-1])]
        return ids, upto[np.searchsorted(starts, offsets)]

    def encode(self, texts: pa.Array) -> tuple[np.ndarray, np.ndarray]:
        """(ids of all texts end to end, n + 1 offsets)."""
        odd = None
        for s in self.special:
            hit = pc.match_substring(texts, s).to_numpy(zero_copy_only=False)
            odd = hit if odd is None else odd | hit
        if odd is None or not odd.any():
            return self._plain(texts)
        parts, plain = [], [[(None, t)] if not o else self._split(t) for t, o in zip(texts.to_pylist(), odd)]
        ids, ends = self._plain(pa.array([t for row in plain for k, t in row if k is None], pa.large_string()))
        i, bounds = 0, [0]
        for row in plain:
            for k, _ in row:
                if k is None:
                    parts.append(ids[ends[i] : ends[i + 1]])
                    i += 1
                else:
                    parts.append(np.array([k], np.int32))
            bounds.append(bounds[-1] + sum(map(len, parts[len(parts) - len(row) :])) if row else bounds[-1])
        return np.concatenate(parts) if parts else np.zeros(0, np.int32), np.array(bounds, np.int64)

    def _split(self, text: str) -> list[tuple[int | None, str]]:
        out, at = [], 0
        for m in self.specials.finditer(text):
            out += [(None, text[at : m.start()]), (self.special[m[0]], m[0])]
            at = m.end()
        return [*out, (None, text[at:])]

    def decode(self, ids) -> str:
        return b"".join(map(self.bytes_of.__getitem__, ids)).decode("utf-8", "replace")


@lru_cache(2)
def encoder(path: str) -> ForcedBoundaryBPE:
    return ForcedBoundaryBPE(path)


def encode_column(text, path: str | None = None):
    """Column: array<int> of the ids of a text."""
    path = path or model_path()
    bounded_batches()

    @F.arrow_udf(ArrayType(IntegerType()))
    def ids(texts: pa.Array) -> pa.Array:
        flat, ends = [], [np.zeros(1, np.int64)]
        for _, part in text_chunks(iter([pa.record_batch([texts], names=["text"])])):
            i, e = encoder(path).encode(part)
            flat.append(i)
            ends.append(e[1:] + ends[-1][-1])
        values = pa.array(np.concatenate(flat) if flat else np.zeros(0, np.int32))
        return pa.ListArray.from_arrays(pa.array(np.concatenate(ends).astype(np.int32)), values)

    return ids(text)


def decode_column(ids, path: str | None = None):
    """Column: the text of an array of ids; null for null."""
    path = path or model_path()
    bounded_batches()

    @F.arrow_udf(StringType())
    def text(rows: pa.Array) -> pa.Array:
        return pa.array([None if r is None else encoder(path).decode(r) for r in rows.to_pylist()], pa.string())

    return text(ids)


DIGEST = StructType([StructField("n_tokens", LongType()), StructField("ids_sha256", StringType()), StructField("decoded_sha256", StringType())])


def digest_column(text, path: str | None = None):
    """Column: struct of the number of ids and the SHA-256 of the ids and of the text decoded from them; ids stay in the worker."""
    path = path or model_path()
    bounded_batches()

    @F.arrow_udf(DIGEST)
    def digest(texts: pa.Array) -> pa.Array:
        bpe, n, a, b = encoder(path), [], [], []
        for _, part in text_chunks(iter([pa.record_batch([texts], names=["text"])])):
            ids, ends = bpe.encode(part)
            row = ids.tolist()
            for s, e in zip(ends[:-1].tolist(), ends[1:].tolist()):
                own = row[s:e]
                n.append(e - s)
                a.append(hashlib.sha256(b",".join(map(bpe.text_of.__getitem__, own))).hexdigest())
                b.append(hashlib.sha256(bpe.decode(own).encode()).hexdigest())
        return pa.StructArray.from_arrays([pa.array(n, pa.int64()), pa.array(a, pa.string()), pa.array(b, pa.string())], names=DIGEST.names)

    return digest(text)


def token_digests(docs: DataFrame, path: str | None = None) -> DataFrame:
    return docs.select("doc_id", digest_column(F.col("text"), path).alias("_d")).select("doc_id", "_d.*")


def op3_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    return token_digests(table(spark, sf_dir, "documents"))


QUERIES = {"op3_bpe": op3_bpe}
ORACLES = {}
