"""Token-id output as wavelet matrices.

Each shard is one file that holds, block by block, the bit-planes of a wavelet
matrix over the token ids, compressed with zstandard, and the document
directory.  ``WaveletMatrix`` answers access, rank (counting) and select
(occurrence lookup) on a decoded block without expanding the ids.

Null and empty texts hold the end id alone.  Rows with a null id come first.
Repeated ids are kept, ordered by text.  Extra columns are ignored, an empty
table gives an empty store.
"""

from __future__ import annotations

import unicodedata
import zlib
from array import array
from functools import lru_cache

import numpy as np
import pyarrow as pa
import zstandard
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .shared import arrow_schema, block_of, partitions, prepare, range_bounds, shared_dir

BLOCK_TOKENS = 1 << 20
SHARD_DDL = "shard int, block int, first bigint, n_tokens bigint, n_docs int, doc_ids array<bigint>, lens array<bigint>, zeros array<bigint>, planes array<binary>"
RANK_STEP = 512


class WaveletMatrix:
    """Bit-planes from the highest bit down; in each plane, symbols with a 0
    go before those with a 1, in stable order."""

    def __init__(self, planes: list[np.ndarray], zeros: list[int], n: int):
        self.planes, self.zeros, self.n = planes, zeros, n
        self._ranks: list[np.ndarray] | None = None

    @classmethod
    def build(cls, ids: np.ndarray, bits: int | None = None) -> WaveletMatrix:
        bits = bits or max(1, int(ids.max(initial=0)).bit_length())
        a, planes, zeros = ids, [], []
        for k in range(bits - 1, -1, -1):
            one = (a >> a.dtype.type(k)) & a.dtype.type(1) != 0
            planes.append(np.packbits(one))
            low = a[~one]
            zeros.append(len(low))
            a = np.concatenate([low, a[one]])
        return cls(planes, zeros, len(ids))

    def _bits(self, k: int) -> np.ndarray:
        return np.unpackbits(self.planes[k], count=self.n).view(bool)

    def decode(self) -> np.ndarray:
        """All symbols in order, bottom plane first."""
        a = np.zeros(self.n, np.uint32 if len(self.planes) > 16 else np.uint16)
        for k in range(len(self.planes) - 1, -1, -1):
            one, z = self._bits(k), self.zeros[k]
            up = np.empty_like(a)
            up[~one] = a[:z]
            up[one] = a[z:] | a.dtype.type(1 << (len(self.planes) - 1 - k))
            a = up
        return a

    def _rank_table(self, k: int) -> np.ndarray:
        """Ones before each RANK_STEP-bit mark of plane k."""
        if self._ranks is None:
            pad = lambda p: np.concatenate([p, np.zeros(-len(p) % (RANK_STEP // 8), np.uint8)])
            self._ranks = [np.concatenate([[0], np.cumsum(np.bitwise_count(pad(p)).reshape(-1, RANK_STEP // 8).sum(1, dtype=np.int64))]) for p in self.planes]
        return self._ranks[k]

    def _rank1(self, k: int, i: int) -> int:
        s = i // RANK_STEP
        part = self.planes[k][s * RANK_STEP // 8 : (i + 7) // 8]
        return int(self._rank_table(k)[s]) + int(np.unpackbits(part, count=i - s * RANK_STEP).sum())

    def access(self, i: int) -> int:
        """Symbol at position i."""
        if not 0 <= i < self.n:
            raise IndexError(i)
        v = 0
        for k, z in enumerate(self.zeros):
            one = self._rank1(k, i + 1) - (r := self._rank1(k, i))
            i = z + r if one else i - r
            v = v << 1 | one
        return v

    def _range(self, sym: int, i: int) -> tuple[int, int]:
        lo, hi = 0, i
        for k, z in enumerate(self.zeros):
            a, b = self._rank1(k, lo), self._rank1(k, hi)
            lo, hi = (z + a, z + b) if sym >> (len(self.zeros) - 1 - k) & 1 else (lo - a, hi - b)
        return lo, hi

    def rank(self, sym: int, i: int | None = None) -> int:
        """How often sym occurs before position i (all, if not given)."""
        if sym >> len(self.zeros):
            return 0
        lo, hi = self._range(sym, self.n if i is None else i)
        return hi - lo

    def _select_bit(self, k: int, bit: int, j: int) -> int:
        t = self._rank_table(k)
        marks = t if bit else np.arange(len(t)) * RANK_STEP - t
        s = int(np.searchsorted(marks, j, "right")) - 1
        part = np.unpackbits(self.planes[k][s * RANK_STEP // 8 : (s + 1) * RANK_STEP // 8])
        return s * RANK_STEP + int(np.flatnonzero(part == bit)[j - int(marks[s])])

    def select(self, sym: int, j: int) -> int:
        """Position of the j-th (from 0) occurrence of sym."""
        if not 0 <= j < self.rank(sym):
            raise IndexError(j)
        i = self._range(sym, self.n)[0] + j
        for k in range(len(self.zeros) - 1, -1, -1):
            bit = sym >> (len(self.zeros) - 1 - k) & 1
            i = self._select_bit(k, bit, i - self.zeros[k] if bit else i)
        return i


@lru_cache(maxsize=2)
def _tokenizer(path: str):
    import os

    os.environ["TOKENIZERS_PARALLELISM"] = "false"
    from tokenizers import Tokenizer

    return Tokenizer.from_file(path)


CACHE_HALVES, CACHE_CHUNKS = 700_000, 500_000
TAIL = b".,!?;:|#$%&*()-"  # ASCII marks that never join letters before them in one piece


def _plain(text: str) -> bool:
    """Whether these are letters that normalising and lower-casing leave alone:
    others may end in a combining mark, which joins the marks behind it."""
    return text.isalpha() and text.lower() == text and unicodedata.is_normalized("NFC", text)


FAR = "\u0530"  # letters before it are the same in all versions of Unicode since
_BYTES = [*range(33, 127), *range(161, 173), *range(174, 256)]  # stand for themselves in a byte-level vocabulary, the others for 256 and up
BYTE_CHARS = {b: b if b in _BYTES else 256 + i for i, b in enumerate([*[b for b in range(256) if b not in _BYTES], *_BYTES])}


def _byte_level(part: bytes) -> str:
    """UTF-8 bytes as the characters of a byte-level vocabulary."""
    return part.decode("latin-1").translate(BYTE_CHARS)


def _bare_letters(tok) -> bool:
    """Whether a run of plain letters reaches the tokenizer's model as it is, byte by byte."""
    letters = "".join(c for c in map(chr, range(ord(FAR))) if _plain(c))
    if tok.pre_tokenizer is None or tok.normalizer is not None and tok.normalizer.normalize_str(letters) != letters:
        return False
    return [name for name, _ in tok.pre_tokenizer.pre_tokenize_str(letters)] == [_byte_level(letters.encode())]


class _Chunks(dict):
    """Ids, as little-endian uint32, of blank-free lower-cased chunks; what is
    missing goes through the library.  A chunk of letters and marks behind them
    is put together from its halves, which are kept apart.  Plain letters go
    straight to the library's model, which is most of the way shorter."""

    def __init__(self, path: str):
        super().__init__()
        self.tok, self.halves = _tokenizer(path), {}
        self.model = self.tok.model if _bare_letters(self.tok) else None

    def _encode(self, part: bytes) -> list[int]:
        text = part.decode()
        if self.model is not None and (part.isalpha() and part.islower() or _plain(text) and max(text) < FAR):
            return [t.id for t in self.model.tokenize(_byte_level(part))]
        return self.tok.encode(text, add_special_tokens=False).ids

    def _half(self, part: bytes) -> bytes:
        got = self.halves.get(part)
        if got is None:
            got = self.halves[part] = array("I", self._encode(part)).tobytes()
        return got

    def __missing__(self, chunk: bytes) -> bytes:
        base = chunk.rstrip(TAIL)
        if base and len(base) < len(chunk) and _plain(base.decode()):
            got = self._half(base) + self._half(chunk[len(base) :])
        else:
            got = self._half(chunk)
        self[chunk] = got
        return got

    def trim(self) -> None:
        if len(self) > CACHE_CHUNKS:
            self.clear()
        if len(self.halves) > CACHE_HALVES:
            self.halves.clear()


_seen: dict[str, _Chunks] = {}


def encode_texts(texts: list[bytes], path: str, end_id: int) -> list[bytes]:
    """Little-endian uint32 ids of each UTF-8 text and then end_id.

    The tokenizer never lets a piece cross white space, nor join letters and
    the marks behind them, so the pieces of a text are those of its blank-free
    chunks and their halves; every distinct half goes through the library once
    per worker while the bounded caches hold it.  Texts that name a special
    token are encoded whole.
    """
    if path not in _seen:
        _seen[path] = _Chunks(path)
    cache = _seen[path]
    cache.trim()
    end, get = int(end_id).to_bytes(4, "little"), cache.__getitem__
    whole = lambda t: np.array(cache.tok.encode(t.decode(), add_special_tokens=False).ids, "<u4").tobytes()
    return [(b"".join(map(get, t.lower().split())) if b"<|" not in t else whole(t)) + end for t in texts]


def write_shards(docs: DataFrame, path: str, tokenizer: str, end_id: int = 2, shards: int | None = None) -> None:
    """Encodes every text and writes one wavelet file per range of ids under path."""
    prepare(docs.sparkSession)
    n = shards or partitions(docs.sparkSession)
    src = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    bounds = range_bounds(src, "doc_id", n)
    schema = arrow_schema(SHARD_DDL)

    def encode(it):
        state = {"shard": 0, "block": 0, "first": 0, "ids": [], "lens": [], "n": 0, "any": []}
        zip_ = zstandard.ZstdCompressor(level=1)

        def flush():
            ids = np.frombuffer(b"".join(state["any"]), "<u4")
            small = ids.astype(np.uint16) if ids.max(initial=0) < 65536 else ids
            wm = WaveletMatrix.build(small)
            out = pa.RecordBatch.from_pylist([{"shard": state["shard"], "block": state["block"], "first": state["first"], "n_tokens": len(ids), "n_docs": len(state["ids"]), "doc_ids": state["ids"], "lens": state["lens"], "zeros": wm.zeros, "planes": [zip_.compress(p.tobytes()) for p in wm.planes]}], schema=schema)
            state.update(block=state["block"] + 1, first=state["first"] + len(ids), ids=[], lens=[], any=[], n=0)
            return out

        for batch in it:
            names = batch.schema.names
            ids, texts = batch.column(names.index("doc_id")).to_pylist(), batch.column(names.index("text")).cast(pa.binary())
            if len(ids):
                state["shard"] = batch.column(names.index("shard"))[0].as_py()
            for a in range(0, len(ids), 512):
                for i, e in zip(ids[a : a + 512], encode_texts([t or b"" for t in texts.slice(a, 512).to_pylist()], tokenizer, end_id)):
                    state["ids"].append(i)
                    state["lens"].append(len(e) // 4)
                    state["any"].append(e)
                    state["n"] += len(e) // 4
                    if state["n"] >= BLOCK_TOKENS:
                        yield flush()
        if state["ids"]:
            yield flush()

    dealt = src.withColumn("shard", block_of("doc_id", bounds)).repartitionById(len(bounds) + 1, F.col("shard")).sortWithinPartitions("doc_id", "text")
    dealt.mapInArrow(encode, SHARD_DDL).write.parquet(path)


def load_block(row: dict) -> WaveletMatrix:
    unzip = zstandard.ZstdDecompressor()
    return WaveletMatrix([np.frombuffer(unzip.decompress(p), np.uint8) for p in row["planes"]], list(row["zeros"]), row["n_tokens"])


def read_documents(spark, path: str, digest=None) -> DataFrame:
    """Documents of a store: doc_id, start, n_tokens and ids (or what digest
    (name, ddl type, function of the ids as '<u4' array) makes of them)."""
    prepare(spark)
    store = spark.read.parquet(path)
    totals = {r["shard"]: r["n"] for r in store.groupBy("shard").agg(F.sum("n_tokens").alias("n")).collect()}  # one number a shard
    before, at = {}, 0
    for s in sorted(totals):
        before[s] = at
        at += totals[s]
    name, kind, fn = digest or ("ids", "array<bigint>", lambda a: a.tolist())
    ddl = f"doc_id bigint, start bigint, n_tokens bigint, {name} {kind}"
    schema = arrow_schema(ddl)
    def decode(it):
        for batch in it:
            for row in batch.to_pylist():
                ids = load_block(row).decode().astype("<u4")
                start = before[row["shard"]] + row["first"]
                ends = np.cumsum(row["lens"])
                parts = np.split(ids, ends[:-1])
                yield pa.RecordBatch.from_pydict({"doc_id": row["doc_ids"], "start": (start + ends - np.array(row["lens"], np.int64)), "n_tokens": row["lens"], name: [fn(p) for p in parts]}, schema=schema)

    return store.mapInArrow(decode, ddl)


def ids_crc32(ids: np.ndarray) -> int:
    return zlib.crc32(ids.astype("<u4").tobytes())


def store_path(spark) -> str:
    import uuid

    return f"{shared_dir(spark)}/segraph/tokens-{uuid.uuid4().hex}"
