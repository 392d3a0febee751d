"""Token ids as directly addressable codes.

Ids are cut into eight-bit chunks, one level for each chunk. A level keeps its
chunks, a bitmap that says which values go on at the next level, and a rank
directory that counts the set bits before each block, so the ids of any
position or range are read without decoding what stands before them.

Null texts count as empty. Empty documents hold the end id alone. Rows that
repeat are each written; equal ids come in the order of their text's hash.
Null ids stand first. An empty table gives an empty file and no rows. Other
columns of the input are ignored.
"""

from __future__ import annotations

import struct
import zlib

import numpy as np
import pandas as pd
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import held, released, scratch_path, shuffle_parts, table

MAGIC = b"DACF"
RANK_BITS = 512
BLOB_SCHEMA = "part int, seq int, local_start long, n_docs int, n_ids long, payload binary"
DOC_SCHEMA = "doc_id long, start long, n_tokens long, ids_crc32 long"


# --- the code itself -------------------------------------------------------------------------

def pack_codes(ids: np.ndarray) -> bytes:
    """Level by level: value count, chunks, continuation bitmap, rank directory."""
    values, out, levels = ids.astype(np.uint32), [], 0
    while levels == 0 or len(values):
        rest = values >> 8
        more = rest > 0
        bits = np.packbits(more, bitorder="little")
        padded = np.zeros(-(-max(len(values), 1) // RANK_BITS) * RANK_BITS, bool)
        padded[:len(more)] = more
        rank = np.concatenate([[0], np.cumsum(padded.reshape(-1, RANK_BITS).sum(1))]).astype("<u4")
        out += [struct.pack("<QII", len(values), len(bits), len(rank)), (values & 255).astype(np.uint8).tobytes(), bits.tobytes(), rank.tobytes()]
        values, levels = rest[more], levels + 1
    return struct.pack("<4sI", MAGIC, levels) + b"".join(out)


class Codes:
    """Random access to packed codes: ``codes[i]`` and ``codes.slice(a, b)``."""

    def __init__(self, payload: bytes | memoryview):
        magic, levels = struct.unpack_from("<4sI", payload, 0)
        if magic != MAGIC:
            raise ValueError("not a file of directly addressable codes")
        self.levels, at = [], 8
        for _ in range(levels):
            n, n_bits, n_rank = struct.unpack_from("<QII", payload, at)
            chunks = np.frombuffer(payload, np.uint8, n, at + 16)
            bits = np.frombuffer(payload, np.uint8, n_bits, at + 16 + n)
            rank = np.frombuffer(payload, "<u4", n_rank, at + 16 + n + n_bits)
            self.levels.append((chunks, bits, rank))
            at += 16 + n + n_bits + 4 * n_rank

    def __len__(self) -> int:
        return len(self.levels[0][0])

    def _before(self, level: int, i: int) -> int:
        """Set bits before position i: the directory's count and those of one block."""
        _, bits, rank = self.levels[level]
        block = i // RANK_BITS
        first = block * RANK_BITS // 8
        inside = np.unpackbits(bits[first:-(-i // 8)], bitorder="little")[:i - block * RANK_BITS]
        return int(rank[block]) + int(inside.sum())

    def slice(self, a: int, b: int, level: int = 0) -> np.ndarray:
        chunks, bits, _ = self.levels[level]
        out = chunks[a:b].astype(np.uint32)
        more = np.unpackbits(bits[a // 8:-(-b // 8)], bitorder="little")[a % 8:a % 8 + b - a].astype(bool)
        if more.any():
            first = self._before(level, a)
            out[more] |= self.slice(first, first + int(more.sum()), level + 1) << 8
        return out

    def __getitem__(self, i: int) -> int:
        value, shift = 0, 0
        for level, (chunks, bits, _) in enumerate(self.levels):
            value |= int(chunks[i]) << shift
            if not bits[i // 8] >> (i % 8) & 1:
                break
            i, shift = self._before(level, i), shift + 8
        return value


# --- the tokenizer, over many texts at once --------------------------------------------------

class PieceEncoder:
    """The byte-level vocabulary of a ``tokenizers`` file, applied to whole batches.

    The library encodes each distinct piece once; how a text splits into pieces
    (runs of letters, digits, other signs and white space, and the contractions)
    is computed for all characters of a batch together. Pieces are independent of
    each other in such a tokenizer, so the ids are those of the library. With
    ``added`` texts are first split at the file's added tokens, which are one id
    each, as the library does unless told to read them as ordinary text.
    """

    CONTRACTIONS = ("s", "t", "re", "ve", "m", "ll", "d")  # fixed values of the pattern

    def __init__(self, path: str, span: int = 1 << 19, slots: int = 1 << 20, keep: int = 1 << 23, added: bool = False):
        import regex
        from tokenizers import Tokenizer

        self.tok = Tokenizer.from_file(path)
        self.tok.encode_special_tokens = not added
        self.added = {t.content: i for i, t in self.tok.get_added_tokens_decoder().items()} if added else {}
        if added and any(t.lstrip or t.rstrip or t.single_word for t in self.tok.get_added_tokens_decoder().values()):
            raise ValueError("added tokens that take in what stands beside them are not supported")
        self.marks = regex.compile("(" + "|".join(map(regex.escape, sorted(self.added, key=len, reverse=True))) + ")") if self.added else None
        vocab = self.tok.get_vocab()
        self.opens = np.zeros(max(vocab.values()) + 1, bool)
        self.opens[[i for t, i in vocab.items() if t.startswith("Ġ")]] = True
        points = np.arange(0x110000, dtype="<u4")
        points[0xD800:0xE000] = 0xFFFD
        every = points.tobytes().decode("utf-32-le")
        self.kind = np.full(0x110000, 3, np.uint8)
        for value, pattern in ((1, r"\p{L}+"), (2, r"\p{N}+"), (0, r"\p{White_Space}+")):
            for m in regex.finditer(pattern, every):
                self.kind[m.start():m.end()] = value
        rng = np.random.default_rng(7)
        self.base = np.uint64(int(rng.integers(1 << 62)) * 2 + 1)
        self.mix = np.uint64(int(rng.integers(1 << 62)) * 2 + 1)
        self.span, self.keep = span, keep
        self.shift = np.uint64(64 - slots.bit_length() + 1)
        self.keys, self.at, self.n = np.zeros(slots, np.uint64), np.zeros(slots, np.int64), np.zeros(slots, np.int64)
        self.ids, self.used = np.zeros(1 << 16, np.uint32), 0
        self._powers(span + 1)

    def _powers(self, n: int) -> None:
        inverse = np.uint64(pow(int(self.base), -1, 1 << 64))
        self.up = np.cumprod(np.full(n, self.base, np.uint64))
        self.down = np.cumprod(np.full(n, inverse, np.uint64))

    def _learn(self, pieces: list[str]) -> tuple[np.ndarray, np.ndarray]:
        """Where the ids of each piece stand, and how many they are."""
        at, n = np.zeros(len(pieces), np.int64), np.zeros(len(pieces), np.int64)
        together = np.flatnonzero([len(p) > 1 and p[0] == " " and p[1:].isalpha() for p in pieces])
        joined = np.array(self.tok.encode_batch_fast(["".join([pieces[k] for k in together.tolist()])], add_special_tokens=False)[0].ids, np.uint32)
        cuts = np.append(np.flatnonzero(self.opens[joined]), len(joined))
        if len(cuts) - 1 == len(together):
            at[together], n[together] = self._store(joined) + cuts[:-1], np.diff(cuts)
            alone = np.setdiff1d(np.arange(len(pieces)), together, assume_unique=True)
        else:
            alone = np.arange(len(pieces))
        ids = [e.ids for e in self.tok.encode_batch_fast([pieces[k] for k in alone.tolist()], add_special_tokens=False)]
        n[alone] = [len(e) for e in ids]
        first = self._store(np.array([i for e in ids for i in e], np.uint32))
        at[alone] = first + np.cumsum(n[alone]) - n[alone]
        return at, n

    def _store(self, ids: np.ndarray) -> int:
        while self.used + len(ids) > len(self.ids):
            self.ids = np.concatenate([self.ids, np.zeros_like(self.ids)])
        self.ids[self.used:self.used + len(ids)] = ids
        self.used += len(ids)
        return self.used - len(ids)

    def _starts(self, points: np.ndarray, kind: np.ndarray, first: np.ndarray) -> np.ndarray:
        """Where pieces start; ``first`` marks the first character of each text."""
        n = len(points)
        white = kind == 0
        before_white, before_kind, before_blank = np.roll(white, 1), np.roll(kind, 1), np.roll(points == 32, 1)
        last = np.roll(first, -1)
        last[-1] = True
        next_black = ~np.roll(white, -1) & ~last
        start = first | (white & (~before_white | next_black)) | (~white & ((before_white & ~before_blank) | (~before_white & (kind != before_kind))))
        for i in np.flatnonzero((points == 39) & start):
            stop = min(n, i + 3)
            ends = np.flatnonzero(first[i + 1:stop])
            after = "".join(map(chr, points[i + 1:i + 1 + ends[0] if len(ends) else stop]))
            hit = next((c for c in self.CONTRACTIONS if after.startswith(c)), None)
            if hit:
                start[i + 1:i + 1 + len(hit)] = False
                if i + 1 + len(hit) < n:
                    start[i + 1 + len(hit)] = True
        return start

    def _span(self, texts: list[str]) -> list[np.ndarray]:
        whole = "".join(texts)
        ends = np.cumsum([len(t) for t in texts])
        if not whole:
            return [np.zeros(0, np.uint32)] * len(texts)
        points = np.frombuffer(whole.encode("utf-32-le", "surrogatepass"), np.uint32)
        n = len(points)
        if n > len(self.up):
            self._powers(n)
        first = np.zeros(n, bool)
        heads = ends - [len(t) for t in texts]
        first[heads[heads < ends]] = True
        start = np.flatnonzero(self._starts(points, self.kind[points], first))
        stop = np.append(start[1:], n)
        code = (points.astype(np.uint64) + np.uint64(1)) * self.mix
        code ^= code >> np.uint64(29)
        total = np.cumsum(code * self.up[:n])
        upto = np.where(start > 0, total[start - 1], np.uint64(0))
        hashes = (total[stop - 1] - upto) * self.down[start] + (stop - start).astype(np.uint64)
        slot = (hashes >> self.shift).astype(np.int64)
        new = np.flatnonzero(self.keys[slot] != hashes)
        at, n_ids = self.at[slot], self.n[slot]
        if len(new):
            # a table with one place for each slot: what it lacks is learnt, once for each piece of the span
            if self.used > self.keep:  # all is forgotten, so memory is bounded
                self.keys[:], self.used = 0, 0
                new = np.arange(len(hashes))
            fresh, where, back = np.unique(hashes[new], return_index=True, return_inverse=True)
            where = new[where]
            fresh_at, fresh_n = self._learn([whole[a:b] for a, b in zip(start[where].tolist(), stop[where].tolist(), strict=True)])
            at[new], n_ids[new] = fresh_at[back], fresh_n[back]
            self.keys[slot[where]], self.at[slot[where]], self.n[slot[where]] = fresh, fresh_at, fresh_n
        upto = np.concatenate([[0], np.cumsum(n_ids)])
        ids = self.ids[np.arange(upto[-1]) + np.repeat(at - upto[:-1], n_ids)]
        cuts = upto[np.searchsorted(start, ends)]
        return np.split(ids, cuts[:-1])

    def encode(self, texts: list[str]) -> list[np.ndarray]:
        """Ids of each text; added tokens stand for themselves, what is between them is encoded as texts are."""
        if not self.marks or not any(t in text for text in texts for t in self.added):
            return self._ordinary(texts)
        parts = [self.marks.split(text) for text in texts]  # ordinary text and added tokens in turn
        between = iter(self._ordinary([p for part in parts for p in part[::2]]))
        ids = [[np.array([self.added[p]], np.uint32) if k % 2 else next(between) for k, p in enumerate(part)] for part in parts]
        return [np.concatenate(x) for x in ids]

    def _ordinary(self, texts: list[str]) -> list[np.ndarray]:
        """Texts are taken together up to ``span`` characters; a longer one is cut where white space begins."""
        out: list[np.ndarray] = []
        taken: list[str] = []
        size = 0
        for text in texts:
            if size and size + len(text) > self.span:
                out += self._span(taken)
                taken, size = [], 0
            if len(text) > self.span:
                out.append(np.concatenate([self._span([p])[0] for p in self._cut(text)]))
            else:
                taken.append(text)
                size += len(text)
        return out + (self._span(taken) if taken else [])

    def _cut(self, text: str) -> list[str]:
        import re

        parts, at = [], 0
        edge = re.compile(r"\S(?=[ \n\t])")
        while len(text) - at > self.span:
            m = edge.search(text, at + self.span - 1)
            if not m:
                break
            parts.append(text[at:m.end()])
            at = m.end()
        return [*parts, text[at:]]


def encoder_of(path: str) -> PieceEncoder:
    """One encoder for each worker process, so tasks share what it has learnt."""
    return held("tokens", path, lambda p: PieceEncoder(p, added=True))


# --- files -----------------------------------------------------------------------------------

def _blob(doc_ids: list, counts: list[int], ids: list[np.ndarray]) -> bytes:
    known = np.array([d is not None and d == d for d in doc_ids], np.uint8)
    numbers = np.array([int(d) if k else 0 for d, k in zip(doc_ids, known, strict=True)], "<i8")
    head = struct.pack("<Q", len(counts)) + known.tobytes() + numbers.tobytes() + np.array(counts, "<u8").tobytes()
    return head + pack_codes(np.concatenate(ids) if ids else np.zeros(0, np.uint32))


def open_blob(payload: bytes) -> tuple[list, np.ndarray, Codes]:
    """Ids of the documents (None for null), where each one's ids start and end, and the codes."""
    (n,) = struct.unpack_from("<Q", payload, 0)
    known = np.frombuffer(payload, np.uint8, n, 8)
    numbers = np.frombuffer(payload, "<i8", n, 8 + n)
    counts = np.frombuffer(payload, "<u8", n, 8 + 9 * n)
    return [int(d) if k else None for d, k in zip(numbers, known, strict=True)], np.concatenate([[0], np.cumsum(counts)]).astype(np.int64), Codes(memoryview(payload)[8 + 17 * n:])


def write_codes(docs: DataFrame, path: str, tokenizer: str, end_id: int = 2, blob_ids: int = 1 << 20) -> None:
    """Writes the ids of all texts, by ascending doc_id, as blobs of about ``blob_ids`` ids.

    One range shuffle orders the documents; each task encodes its range as a
    stream and holds one blob at most. The files are committed by Spark's own
    writer, so any store that Spark writes to will do and a lost executor's
    task is simply run again.
    """
    def encode(batches):
        encoder, part = encoder_of(tokenizer), TaskContext.get().partitionId()
        seq, start, size = 0, 0, 0
        doc_ids, counts, taken = [], [], []

        def flush():
            nonlocal seq, start, size, doc_ids, counts, taken
            row = pd.DataFrame({"part": [part], "seq": [seq], "local_start": [start], "n_docs": [len(counts)], "n_ids": [size], "payload": [_blob(doc_ids, counts, taken)]})
            seq, start, size = seq + 1, start + size, 0
            doc_ids, counts, taken = [], [], []
            return row

        tail = np.array([end_id], np.uint32)
        for pdf in released(batches):
            for lo in range(0, len(pdf), 256):
                some = pdf.iloc[lo:lo + 256]
                known = some["known"].tolist()
                for doc_id, ok, ids in zip(some["doc_id"].tolist(), known, encoder.encode(some["text"].tolist()), strict=True):
                    doc_ids.append(doc_id if ok else None)
                    taken += [ids, tail]
                    counts.append(len(ids) + 1)
                    size += len(ids) + 1
                    if size >= blob_ids:
                        yield flush()
        if counts:
            yield flush()

    spark = docs.sparkSession
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.coalesce(F.col("text"), F.lit("")).alias("text"))
    rows = rows.select(F.col("doc_id").isNotNull().alias("known"), F.coalesce("doc_id", F.lit(-(1 << 63))).alias("doc_id"), "text")
    order = [F.col("known"), F.col("doc_id"), F.xxhash64("text")]
    ranged = rows.repartitionByRange(shuffle_parts(spark), *order).sortWithinPartitions(*order)
    ranged.mapInPandas(encode, BLOB_SCHEMA).write.parquet(path)


def read_codes(spark: SparkSession, path: str) -> DataFrame:
    """One row per document from the files: where its ids start, how many, and their checksum.

    Where each part starts is a running sum over parts, of which there are as
    many as the writer had shuffle partitions.
    """
    blobs = spark.read.schema(BLOB_SCHEMA).parquet(path)
    parts = sorted((r["part"], r["n"]) for r in blobs.groupBy("part").agg(F.sum("n_ids").alias("n")).collect())
    starts, total = [], 0
    for part, n in parts:
        starts.append((part, total))
        total += n
    first = spark.createDataFrame(starts, "part int, part_start long")

    def decode(batches):
        for pdf in released(batches):
            for base, payload in zip(pdf["start"].tolist(), pdf["payload"].tolist(), strict=True):
                doc_ids, edges, codes = open_blob(payload)
                sums = [zlib.crc32(codes.slice(int(a), int(b)).astype("<u4").tobytes()) for a, b in zip(edges[:-1], edges[1:], strict=True)]
                yield pd.DataFrame({"doc_id": pd.array(doc_ids, "Int64"), "start": base + edges[:-1], "n_tokens": np.diff(edges), "ids_crc32": np.array(sums, np.int64)})

    located = blobs.join(F.broadcast(first), "part").select((F.col("local_start") + F.col("part_start")).alias("start"), "payload")
    return located.mapInPandas(decode, DOC_SCHEMA)


def default_tokenizer() -> str:
    import public_tokenizers

    return public_tokenizers.path("byte_bpe_50k.json")


def token_codes(docs: DataFrame, tokenizer: str | None = None, end_id: int = 2, path: str | None = None) -> DataFrame:
    """Writes the files and reads them back."""
    spark = docs.sparkSession
    path = path or scratch_path(spark, "token-codes")
    write_codes(docs, path, tokenizer or default_tokenizer(), end_id)
    return read_codes(spark, path)


def op10_token_codes(spark: SparkSession, sf_dir: str) -> DataFrame:
    return token_codes(table(spark, sf_dir, "documents"))
