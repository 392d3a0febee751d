"""Benchmark decontamination by random-walk embedding, bit sampling and exact edit verification.

A random walk reads a window character by character: at each step it writes the
character it stands on and moves on or stays, as a fixed random table of step
and character says. Texts at a small edit distance fall into step again, so
their walks differ in few places (edit distance becomes Hamming distance), and a
sample of places agrees with fair probability. Independent walks and samples
are taken at every word of a document, and inside long runs without a blank.
Items are entered from each of their words up to ``TAIL`` bytes before their
end, so the window of an item's size is covered by walks all along it, and an
edited passage is met where any of them agrees. How many walks, and of which
length, follows from the length of the item (``CLASSES``): so many that an item
with ``EDITS`` edits at random places meets at least one with probability
``TARGET`` (tests measure it for each length).

Items under ``LEAST`` bytes are too short for walks. They are met without loss:
of one more pieces than edits are allowed, one stands unchanged in any text that
near, so every place that holds a piece is a candidate. Items so short that no
edit is allowed (under five bytes) are looked for as whole words.

Of the candidates those are left out that hold fewer of the item's three-byte
pieces, each about where it should be, than any text within ``EDITS`` must (an
edit changes one of pieces that do not overlap, so none is lost). The others are
verified: the edit distance of the whole item to the best-placed part of the
document, by bit-parallel dynamic programming, must be at most ``EDITS`` of the
item's length.

Texts are compared in lower case with runs of white space as one blank. Null
texts and items count as empty; empty items and items with a null id match
nothing. Rows that repeat are each reported; items that repeat under one id
count once. Items come in blocks of at most ``ITEM_BLOCK`` rows or
``BLOCK_BYTES``, one at a time, so what the driver holds and what is sent to the
executors is bounded; each block more is one pass more over the documents, whose
result is a table in the shared folder. An empty table gives no rows. Other
columns pass through ``drop_leaks``.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import held, materialize, released, table

TARGET = 0.95
# Least length of an item, then walks, steps and sampled places that reach TARGET from that length on. Where steps and
# places are the same, longer items use the first of the walks that shorter ones need.
CLASSES = ((40, 16, 36, 9), (80, 6, 32, 12), (120, 3, 32, 12), (170, 2, 32, 12))
TAIL, RUN, PAD = 16, 24, 64
EDITS = 0.2
LEAST, WORDLIKE = 40, 5
ITEM_BLOCK, BLOCK_BYTES = 20_000, 16 << 20
BATCH, CELLS = 1 << 21, 1 << 22


def plain(text: str | None) -> bytes:
    return " ".join((text or "").lower().split()).encode("utf-8", "replace")


class Walker:
    def __init__(self, walks: int, steps: int, sample: int):
        each = [np.random.default_rng([31, w]) for w in range(walks)]  # a walk is the same however many there are
        self.moves = np.array([rng.integers(0, 2, (steps, 256)) for rng in each], np.intp)
        self.picked = [np.sort(rng.choice(steps, sample, replace=False)) for rng in each]
        self.salt = np.array([rng.integers(1, 1 << 63) for rng in each], np.uint64)
        self.steps = steps

    def keys(self, data: np.ndarray, starts: np.ndarray) -> np.ndarray:
        """One key per walk and start; ``data`` must be padded by the number of steps."""
        out = np.empty((len(self.moves), len(starts)), np.uint64)
        for a in range(0, len(starts), 1 << 14):  # few enough to stay in the processor's cache
            first = starts[a:a + (1 << 14)].astype(np.intp)
            c, step = np.empty(len(first), np.uint8), np.empty(len(first), np.intp)
            for w, moves in enumerate(self.moves):
                at, key, picked = first.copy(), np.full(len(first), self.salt[w]), set(self.picked[w].tolist())
                for j in range(int(self.picked[w][-1]) + 1):
                    data.take(at, out=c, mode="clip")
                    if j in picked:
                        key ^= c
                        key *= np.uint64(0x9E3779B97F4A7C15)
                        key ^= key >> np.uint64(29)
                    moves[j].take(c, out=step, mode="clip")
                    at += step
                out[w, a:a + len(first)] = key
        return out


def word_starts(data: np.ndarray) -> np.ndarray:
    """Places after a blank or a separator (0), and the first; in runs over RUN bytes also those that two bytes choose."""
    if not len(data):
        return np.zeros(0, np.int64)
    edge = (data == 32) | (data == 0)
    start = np.concatenate([[True], edge[:-1]]) & ~edge
    first = np.flatnonzero(start)
    ends = np.append(np.flatnonzero(edge), len(data))
    stop = ends[np.searchsorted(ends, first)]
    for a, b in zip(first[stop - first > RUN].tolist(), stop[stop - first > RUN].tolist(), strict=True):
        two = data[a:b - 1].astype(np.uint32) * 251 + data[a + 1:b]
        start[a + 1:b] |= (two * np.uint32(0x9E3779B1)) >> np.uint32(29) == 0
    return np.flatnonzero(start)


def pieces_of(data: np.ndarray) -> np.ndarray:
    """A 16-bit number for the three bytes at each place but the last two."""
    d = data.astype(np.uint32)
    return (((d[:-2] << 16 | d[1:-1] << 8 | d[2:]) * np.uint32(0x9E3779B1)) >> np.uint32(16)).astype(np.uint16)


def edit_distances(items: list[bytes], texts: list[bytes], most: list[int]) -> tuple[np.ndarray, np.ndarray]:
    """For each pair the least edits between the item and any part of the text, and where that part ends.

    Bit-parallel over 64 bytes of the item at a time, all pairs together: a word's
    horizontal differences at every place of the text are handed to the next word.
    Pairs with more than ``most`` edits get one more than that, and drop out as
    soon as the first words alone need as many.
    """
    best, end = np.array(most, np.int64) + 1, np.zeros(len(items), np.int64)
    order, first = sorted(range(len(items)), key=lambda k: (len(texts[k]), len(items[k]))), 0
    for k in range(len(order)):
        if (k + 1 - first) * len(texts[order[k]]) > CELLS or k + 1 == len(order):
            some = order[first:k + 1]
            if len(some) > 12 * (max(len(items[x]) for x in some) // 64 + 1):
                best[some], end[some] = _distances([items[x] for x in some], [texts[x] for x in some], best[some] - 1)
            else:  # too few for a step over all of them to pay
                for x in some:
                    low, at = _distance(items[x], texts[x])
                    if low < best[x]:
                        best[x], end[x] = low, at
            first = k + 1
    return best, end


def _distance(item: bytes, text: bytes) -> tuple[int, int]:
    """One pair, the whole item as the bits of one number."""
    m = len(item)
    rows: dict[int, int] = {}
    for i, c in enumerate(item):
        rows[c] = rows.get(c, 0) | (1 << i)
    full, top = (1 << m) - 1, 1 << max(m - 1, 0)
    up, down, score, best, end = full, 0, m, m, 0
    for k, c in enumerate(text if m else b""):
        eq = rows.get(c, 0)
        cross = eq | down
        x = (((eq & up) + up) ^ up) | eq
        plus, minus = down | (full & ~(x | up)), up & x
        score += bool(plus & top) - bool(minus & top)
        plus, minus = (plus << 1) & full, (minus << 1) & full
        up, down = minus | (full & ~(cross | plus)), plus & cross
        if score < best:
            best, end = score, k + 1
    return best, end


def _distances(items: list[bytes], texts: list[bytes], most: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    one = np.uint64(1)
    length, reach = np.array([len(i) for i in items]), np.array([len(t) for t in texts])
    steps = int(reach.max(initial=0))
    text = np.zeros((steps, len(items)), np.uint8)
    for k, t in enumerate(texts):
        text[:len(t), k] = np.frombuffer(t, np.uint8)
    best, end = np.minimum(length, most + 1), np.zeros(len(items), np.int64)
    own, flows = np.arange(len(items)), np.zeros(text.shape, np.int8)
    word = 0
    while len(own):
        parts = [items[k][64 * word:64 * word + 64] for k in own.tolist()]
        sizes = np.array([len(x) for x in parts])
        rows = np.zeros(len(own) * 256, np.uint64)
        place = np.arange(sizes.sum()) - np.repeat(np.cumsum(sizes) - sizes, sizes)
        np.bitwise_or.at(rows, np.repeat(np.arange(len(own)) * 256, sizes) + np.frombuffer(b"".join(parts), np.uint8), one << place.astype(np.uint64))
        top, base = (sizes - 1).astype(np.uint64), np.arange(len(own)) * 256
        up, down = np.full(len(own), ~np.uint64(0)), np.zeros(len(own), np.uint64)
        for j in range(steps):
            flow = flows[j]
            less = (flow < 0).astype(np.uint64)
            eq = rows[base + text[j]]
            cross = eq | down
            eq |= less
            x = (((eq & up) + up) ^ up) | eq
            plus, minus = down | ~(x | up), up & x
            out = ((plus >> top) & one).astype(np.int8)
            out -= ((minus >> top) & one).astype(np.int8)
            plus, minus = (plus << one) | (flow > 0), (minus << one) | less
            up, down = minus | ~(cross | plus), plus & cross
            flows[j] = out
        done = np.minimum(length[own], 64 * word + 64)
        score = done + np.cumsum(flows, 0, np.int32)
        score[np.arange(steps)[:, None] >= reach[own]] = 1 << 30
        low = np.minimum(done, score.min(0, initial=1 << 30))
        last = length[own] <= 64 * word + 64
        hit = own[last & (low <= best[own]) & (low < length[own])]
        at = np.flatnonzero(last & (low <= best[own]) & (low < length[own]))
        best[hit], end[hit] = low[at], (score[:, at] == low[at]).argmax(0) + 1
        on = np.flatnonzero(~last & (low <= most[own]))
        own, flows, text = own[on], flows[:, on], text[:, on]
        word += 1
    return best, end


def edit_distance(item: bytes, text: bytes) -> tuple[int, int]:
    """``edit_distances`` of one pair."""
    best, end = edit_distances([item], [text], [len(item)])
    return int(best[0]), int(end[0])


class Group:
    """Items that are met by the same kind of walks, with the keys of their words."""

    def __init__(self, items: list[tuple[int, bytes]], walks: dict[int, int], steps: int, sample: int):
        self.walker = Walker(max(walks.values()), steps, sample)
        parts, base, item, offset, starts = [], 0, [], [], []
        for i in walks:
            data = np.frombuffer(items[i][1], np.uint8)
            s = word_starts(data)
            s = s[s <= len(data) - TAIL]
            parts += [data, np.zeros(PAD, np.uint8)]
            starts.append(s + base)
            offset.append(s)
            item.append(np.full(len(s), i))
            base += len(data) + PAD
        keys, item = self.walker.keys(np.concatenate(parts), np.concatenate(starts)), np.concatenate(item)
        used = np.arange(len(keys))[:, None] < np.array([walks[i] for i in item.tolist()])
        keys, item, offset = keys[used], np.broadcast_to(item, used.shape)[used], np.broadcast_to(np.concatenate(offset), used.shape)[used]
        order = np.argsort(keys, kind="stable")
        self.keys, self.item, self.offset = keys[order], item[order], offset[order]
        self.bits = np.zeros(1 << 22, bool)
        self.bits[self.keys >> np.uint64(42)] = True

    def meet(self, data: np.ndarray, starts: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(item, begin): where items would begin in ``data`` for the starts that they meet, each once and by item."""
        keys = self.walker.keys(data, starts)
        walk, at = np.nonzero(self.bits[keys >> np.uint64(42)])
        hit = keys[walk, at]
        lo, hi = np.searchsorted(self.keys, hit, "left"), np.searchsorted(self.keys, hit, "right")
        n = hi - lo
        entry = np.repeat(lo - np.cumsum(n) + n, n) + np.arange(n.sum())
        both = np.unique((self.item[entry].astype(np.int64) << 32) + np.repeat(starts[at], n) - self.offset[entry] + (1 << 20))
        return both >> 32, (both & 0xFFFFFFFF) - (1 << 20)


class Pieces:
    """Items under LEAST bytes, met by one of the pieces that edits must leave unchanged."""

    def __init__(self, items: list[tuple[int, bytes]], own: list[int]):
        met: dict[int, set] = {}
        for i in own:
            text = items[i][1]
            cuts = np.linspace(0, len(text), int(EDITS * len(text)) + 2).astype(int)
            for a, b in zip(cuts[:-1].tolist(), cuts[1:].tolist(), strict=True):
                q = min(4, b - a)
                met.setdefault(q, set()).add((int.from_bytes(text[a:a + q], "big"), i, a))
        self.tables = []
        for q, rows in sorted(met.items()):
            code, item, offset = np.array(sorted(rows), np.int64).T
            bits = np.zeros(1 << 16, bool)
            bits[self._slot(code.astype(np.uint32))] = True
            self.tables.append((q, code.astype(np.uint32), item, offset, bits))

    @staticmethod
    def _slot(code: np.ndarray) -> np.ndarray:
        return (code * np.uint32(0x9E3779B1)) >> np.uint32(16)

    def meet(self, data: np.ndarray, starts: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """As ``Group.meet``, at every byte."""
        found = []
        for q, codes, item, offset, bits in self.tables:
            code = np.zeros(len(data) - q + 1, np.uint32)
            for j in range(q):
                code = code << np.uint32(8) | data[j:j + len(code)]
            at = np.flatnonzero(bits[self._slot(code)])
            lo, hi = np.searchsorted(codes, code[at], "left"), np.searchsorted(codes, code[at], "right")
            n = hi - lo
            entry = np.repeat(lo - np.cumsum(n) + n, n) + np.arange(n.sum())
            found.append((item[entry] << 32) + np.repeat(at, n) - offset[entry] + (1 << 20))
        both = np.unique(np.concatenate(found))
        return both >> 32, (both & 0xFFFFFFFF) - (1 << 20)


class Index:
    """Items of one block, entered from each word or by pieces, and those that allow no edit."""

    def __init__(self, items: list[tuple[int, bytes]]):
        self.items, self.groups, self.automaton = items, [], None
        kinds: dict = {}
        for i, (_, t) in enumerate(items):
            if len(t) >= LEAST:
                _, walks, *kind = max(c for c in CLASSES if c[0] <= len(t))
                kinds.setdefault(tuple(kind), {})[i] = walks
        self.groups += [Group(items, walks, *kind) for kind, walks in sorted(kinds.items())]
        if short := [i for i, (_, t) in enumerate(items) if WORDLIKE <= len(t) < LEAST]:
            self.groups.append(Pieces(items, short))
        self.margin = PAD + max((int((1 + EDITS) * len(t)) for _, t in items), default=0)
        if words := [i for i, (_, t) in enumerate(items) if 0 < len(t) < WORDLIKE]:
            import ahocorasick

            self.automaton = ahocorasick.Automaton()
            for i in words:
                word = items[i][1].decode("utf-8", "replace")
                self.automaton.add_word(word, [*self.automaton.get(word, []), i])
            self.automaton.make_automaton()

    def scan(self, texts: list[str | None]) -> list[tuple[int, int, int, int]]:
        """(text, item, edits, start) of every item found in each text; texts are taken together up to BATCH bytes."""
        found, taken, first, size = [], [], 0, 0
        for k, text in enumerate(texts):
            taken.append(plain(text))
            size += len(taken[-1])
            if size >= BATCH or k + 1 == len(texts):
                found += [(first + t, *rest) for t, *rest in self._scan(taken)]
                taken, first, size = [], k + 1, 0
        return found

    def _scan(self, texts: list[bytes]) -> list[tuple[int, int, int, int]]:
        best: dict[tuple[int, int], tuple[int, int]] = {}
        for t, text in enumerate(texts) if self.automaton else ():
            for at, hits in self._words(text.decode("utf-8", "replace")):
                for i in hits:
                    best.setdefault((t, i), (0, at))
        if self.groups:
            data = np.frombuffer(b"".join(t + b"\0" * PAD for t in texts), np.uint8)
            base = np.cumsum([0] + [len(t) + PAD for t in texts])
            starts = word_starts(data)
            pieces = np.pad(pieces_of(data), self.margin)
            for group in self.groups:
                self._verify(texts, base, *self._likely(*group.meet(data, starts), pieces), best)
        return [(t, i, edits, start) for (t, i), (edits, start) in sorted(best.items())]

    def _words(self, text: str):
        """Where items that allow no edit stand as whole words (in bytes), and which."""
        for end, hits in self.automaton.iter(text):
            first = end + 1 - len(self.items[hits[0]][1].decode("utf-8", "replace"))
            if not (first and text[first - 1].isalnum()) and not (end + 1 < len(text) and text[end + 1].isalnum()):
                yield len(text[:first].encode("utf-8", "replace")), hits

    def _likely(self, item: np.ndarray, begin: np.ndarray, pieces: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """The (item, begin) whose surroundings hold enough of the item's pieces, each at most the allowed edits out of place."""
        keep = np.ones(len(item), bool)
        cuts = np.append(np.flatnonzero(np.diff(item, prepend=-1)), len(item))
        first, count = np.zeros(1 << 16, np.int32), np.zeros(1 << 16, np.uint8)
        for a, b in zip(cuts[:-1].tolist(), cuts[1:].tolist(), strict=True):
            text = self.items[int(item[a])][1]
            most = int(EDITS * len(text))
            own = pieces_of(np.frombuffer(text, np.uint8))[::3]  # pieces that do not overlap
            order = np.argsort(own, kind="stable")
            values, at, n = np.unique(own[order], return_index=True, return_counts=True)
            if n.max(initial=0) > 255:  # one piece over and over: all are verified
                continue
            first[values], count[values] = at, n
            reach = np.arange(-most, len(text) + most - 2, dtype=np.int32)
            room = max(1, CELLS // 8 // len(reach))
            for c in range(a, b, room):
                some = np.arange(c, min(b, c + room))
                near = pieces[(begin[some] + self.margin)[:, None] + reach]
                row, col = np.nonzero(count.take(near))
                piece = near[row, col]
                n = count[piece].astype(np.int32)
                if n.max(initial=1) > 1:  # a piece that the item has more than once may be any of them
                    nth = np.arange(n.sum()) - np.repeat(np.cumsum(n) - n, n)
                    row, col, piece = np.repeat(row, n), np.repeat(col, n), np.repeat(piece, n)
                    place = order[first[piece] + nth]
                else:
                    place = order[first[piece]]
                right = np.abs(3 * place - reach[col]) <= most
                met = np.zeros((len(some), len(own)), bool)
                met[row[right], place[right]] = True
                keep[some] = met.sum(1) >= len(own) - most
            count[values] = 0
        return item[keep], begin[keep]

    def _verify(self, texts: list[bytes], base: np.ndarray, item: np.ndarray, begin: np.ndarray, best: dict) -> None:
        tries: dict[tuple[int, int], set] = {}
        of = np.clip(np.searchsorted(base, begin, "right") - 1, 0, len(texts) - 1)
        for i, x, t in zip(item.tolist(), begin.tolist(), of.tolist(), strict=True):
            long = len(self.items[i][1])
            for u in (t, t + 1):  # a passage may begin with less than its item, so before its text
                if u < len(texts) and base[u] < x + long and x - base[u] < len(texts[u]) and best.get((u, i), (1, 0))[0]:
                    at = x - int(base[u])
                    if texts[u][max(at, 0):at + long] == self.items[i][1]:
                        best[u, i] = (0, at)
                    else:
                        tries.setdefault((u, i), set()).add(at)
        windows = []  # places nearer to each other than the edits allowed share one window
        for (u, i), places in tries.items():
            if best.get((u, i), (1, 0))[0]:
                most, first, last = int(EDITS * len(self.items[i][1])), None, 0
                for at in sorted(places):
                    if first is not None and at > first + most:
                        windows.append((u, i, max(0, first - most), last + len(self.items[i][1]) + most))
                        first = None
                    first, last = at if first is None else first, at
                windows.append((u, i, max(0, first - most), last + len(self.items[i][1]) + most))
        own = [self.items[i][1] for _, i, _, _ in windows]
        edits, end = edit_distances(own, [texts[u][lo:hi] for u, _, lo, hi in windows], [int(EDITS * len(x)) for x in own])
        for (u, i, lo, _), x, e, stop in zip(windows, own, edits.tolist(), end.tolist(), strict=True):
            if e <= int(EDITS * len(x)):
                best[u, i] = min(best.get((u, i), (e, 1 << 62)), (e, max(0, lo + stop - len(x))))


def item_blocks(benchmark: DataFrame):
    """The items in blocks of bounded size, each a sorted list, one at a time (one empty block if there are none)."""
    items = benchmark.filter("item_id is not null and text is not null").select(F.col("item_id").cast("long").alias("item_id"), "text").distinct()
    n, size = items.agg(F.count("*"), F.coalesce(F.sum(F.octet_length("text")), F.lit(0))).first()
    blocks = max(1, -(-n // ITEM_BLOCK), -(-size // BLOCK_BYTES))
    if blocks > 1:
        items = materialize(items, "leak-items")
    for b in range(blocks):
        rows = items.filter(F.pmod(F.xxhash64("item_id", "text"), F.lit(blocks)) == b).collect()
        yield sorted({(r["item_id"], plain(r["text"])) for r in rows}), blocks


def find_leaks(docs: DataFrame, benchmark: DataFrame) -> DataFrame:
    """(doc_id, item_id, edits, start): every item found in each row of ``docs``; start is in bytes of the plain text."""
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text")
    found = None
    for block, blocks in item_blocks(benchmark):
        part = rows.mapInPandas(_finder(block), "doc_id long, item_id long, edits int, start long")
        if blocks > 1:  # else every block would stay with the driver until the last is searched
            part = materialize(part, "leaks")
        found = part if found is None else found.unionByName(part)
    return found


def _finder(block: list):
    def find(batches):
        for pdf in released(batches):
            hits = held("leaks", block, Index).scan(pdf["text"].tolist())
            if hits:
                t, i, e, s = map(list, zip(*hits, strict=True))
                yield pd.DataFrame({"doc_id": pdf["doc_id"].astype("Int64").iloc[t].reset_index(drop=True), "item_id": [block[x][0] for x in i], "edits": e, "start": s})

    return find


def drop_leaks(docs: DataFrame, benchmark: DataFrame) -> DataFrame:
    """The rows of ``docs`` that hold no item, with their own columns."""
    kept = docs
    for block, blocks in item_blocks(benchmark):
        kept = kept.filter(_clean_of(block)(F.coalesce(F.col("text"), F.lit(""))))
        if blocks > 1:
            kept = materialize(kept, "clean-of-leaks")
    return kept


def _clean_of(block: list):
    @F.pandas_udf("boolean")
    def clean(batches: Iterator[pd.Series]) -> Iterator[pd.Series]:
        for texts in released(batches):
            hit = {t for t, *_ in held("leaks", block, Index).scan(texts.tolist())}
            yield pd.Series([k not in hit for k in range(len(texts))], dtype=bool)

    return clean


def op7_leak_windows(spark: SparkSession, sf_dir: str) -> DataFrame:
    return find_leaks(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))
