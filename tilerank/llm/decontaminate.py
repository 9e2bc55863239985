"""Benchmark decontamination by the q-gram lemma over diagonal bands, confirmed by banded alignment.

Texts are compared in lower case with each run of other than letters and digits as one space. The windows
of an item are all its parts of WINDOW characters (and the whole item up to WHOLE characters); a document is contaminated
if a part of it is within EDITS of a window's length in edits. Three exact steps, each cheaper than
the next per candidate:

1. k edits leave an untouched run of at least (m - k) / (k + 1) characters, SEED or more by the choice of
   k, so only places that share a SEED-gram with an item are looked at (hash table, whole text);
2. a window of m characters within k edits shares at least m + 1 - q (k + 1) q-grams with the text in a band
   of k diagonals to either side (bands overlap: one is laid around each seed's own diagonal), counted
   for all windows on the diagonal by one running sum;
3. alignment in that band must stay within k.

Items travel to the executors in blocks of ITEM_BLOCK characters at most (about 24 bytes a character in each Python worker), however
many and however long they are; a longer item is cut into overlapping parts. Documents are never shuffled.

Defined cases: null and empty texts hold nothing; items of fewer than MIN_CHARS normal characters are common phrases, so they count
only where they stand alone, as a whole line or a whole text of equal normal form; items without a letter or digit, and null item
ids, are left out; repeated items count once; repeated documents each get a row; without items no document is contaminated; extra
columns pass through unchanged (the added column's name gets an underscore where they have it).
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import free_name

SEED, Q, WINDOW, WHOLE, EDITS, MIN_CHARS = 15, 8, 120, 180, 0.05, 25
#: Windows aligned at once, and seed hits held at once.
BATCH, HITS = 1024, 1 << 20
#: Characters of text worked on at once, and characters of items sent at once.
PIECE, ITEM_BLOCK = 1 << 19, 2 << 20
BASE, SCATTER = np.uint64(0x9E3779B97F4A7C15 | 1), np.uint64(0xD6E8FEB86659FD93)
BITS = 22


def code_table() -> np.ndarray:
    """Code point -> its lower-case letter or digit, or 32."""
    t = np.full(0x110000, 32, np.uint32)
    t[0x10000:] = np.arange(0x10000, 0x110000)
    for c in range(0x10000):
        s = chr(c)
        if s.isalnum():
            low = s.lower()
            t[c] = ord(low) if len(low) == 1 else c
    return t


def normal(text: str | None, table: np.ndarray) -> np.ndarray:
    a = table[np.frombuffer((text or "").encode("utf-32-le", "surrogatepass"), "<u4")]
    if not len(a):
        return a
    blank = a == 32
    keep = ~blank
    keep[1:] |= ~blank[:-1]
    a = a[keep]
    return a[int(a[0] == 32) : len(a) - int(a[-1] == 32)] if len(a) > 1 else a[a != 32]


def grams(a: np.ndarray, n: int) -> np.ndarray:
    """Polynomial hash of every run of n codes, by doubling."""
    if len(a) < n:
        return np.empty(0, np.uint64)
    with np.errstate(over="ignore"):
        power, width, out, at, rest = BASE, 1, None, 0, n
        run = a.astype(np.uint64)
        while rest:
            if rest & 1:
                part = run[at : at + len(a) - n + 1]
                out = part.copy() if out is None else out + part * shift
                at += width
                shift = power if at == width else shift * power
            rest >>= 1
            if rest:
                run = run[:-width] + run[width:] * power
                power, width = power * power, 2 * width
        return (out ^ (out >> np.uint64(31))) * SCATTER


def budget(m: int) -> int:
    """Edits allowed in a window of m characters: EDITS of it, but few enough to leave a seed."""
    return max(0, min(int(EDITS * m), (m - SEED) // (SEED + 1)))


def lengths(m: int) -> list[int]:
    """Window lengths of an item of m characters."""
    return [m] if m <= WINDOW else [WINDOW, m] if m <= WHOLE else [WINDOW]


def windows(m: int) -> list[tuple[int, int]]:
    return [(lo, lo + n) for n in lengths(m) for lo in range(m - n + 1)]


class ItemIndex:
    """Seeds of the items, sorted by hash."""

    def __init__(self, items: list[tuple[int, str]]):
        table = code_table()
        self.ids, self.texts, h, who, at = [], [], [], [], []
        self.short: dict[bytes, list[int]] = {}
        for item, text in items:
            a = normal(text, table)
            if len(a) < MIN_CHARS:
                if len(a):
                    self.short.setdefault(a.tobytes(), []).append(item)
                continue
            g = grams(a, SEED)
            who.append(np.full(len(g), len(self.ids), np.int32))
            self.ids.append(item)
            self.texts.append(a)
            h.append(g)
            at.append(np.arange(len(g), dtype=np.int32))
        self.hash = np.concatenate(h) if h else np.empty(0, np.uint64)
        order = np.argsort(self.hash, kind="stable")
        self.hash = self.hash[order]
        self.who = np.concatenate(who)[order] if who else np.empty(0, np.int32)
        self.at = np.concatenate(at)[order] if at else np.empty(0, np.int32)


def part(a: np.ndarray, lo: int, hi: int, fill: int) -> np.ndarray:
    """a[lo:hi], where places outside of ``a`` hold ``fill``."""
    out = np.full(max(0, hi - lo), fill, a.dtype)
    x, y = max(lo, 0), min(hi, len(a))
    if x < y:
        out[x - lo : y - lo] = a[x:y]
    return out


def band_grams(item: np.ndarray, a: np.ndarray, lo: int, hi: int, d: int, k: int) -> np.ndarray:
    """For each q-gram of item[lo:hi]: whether the text has it within k diagonals of ``d`` (place in text less place in item)."""
    g = grams(item[lo:hi], Q)
    start = max(0, lo + d - k)
    there = grams(a[start : max(start, hi + d + k)], Q)
    if not len(g) or not len(there):
        return np.zeros(len(g), bool)
    # a place without a gram holds 0, which can only let more windows pass
    there = part(there, lo + d - k - start, lo + d + k - start + len(g), 0)
    return (np.lib.stride_tricks.sliding_window_view(there, 2 * k + 1) == g[:, None]).any(1)


def band_distances(item: np.ndarray, a: np.ndarray, los: np.ndarray, n: int, d: int, k: int) -> np.ndarray:
    """Least edits between each window item[lo:lo + n] and a part of the text, along diagonals d - k to d + k."""
    width, far = 2 * k + 1, 1 << 20
    steps = np.arange(width)
    first = int(los.min()) + d - k
    text = part(a, first, int(los.max()) + d + k + n + 1, 0xFFFFFFFF)
    at = los[:, None] + d - k + steps
    row = np.where((at >= 0) & (at <= len(a)), 0, far)
    at -= first
    end = np.full((len(los), 1), far)
    for i in range(n):
        up = np.concatenate([row[:, 1:], end], 1) + 1
        new = np.minimum(row + (text[at + i] != item[los + i][:, None]), up)
        row = np.minimum.accumulate(new - steps, 1) + steps
    return row.min(1)


class Finder:
    """Contaminating items of texts, for one block of items."""

    def __init__(self, index: ItemIndex):
        self.x, self.table = index, code_table()
        self.there = np.zeros(1 << BITS, bool)
        self.there[index.hash >> np.uint64(64 - BITS)] = True

    def confirm(self, a: np.ndarray, item: int, p: np.ndarray, o: np.ndarray) -> bool:
        """Seed hits of one item at places p of the text and o of the item."""
        text = self.x.texts[item]
        m = len(text)
        for n in lengths(m):
            k = budget(n)
            least = n + 1 - Q * (k + 1)
            for d in np.unique(p - o).tolist():
                seeds = o[p - o == d]
                # windows that hold a seed of this diagonal
                lo, hi = max(0, int(seeds.min()) + SEED - n), min(m, int(seeds.max()) + n)
                same = np.concatenate(([0], np.cumsum(text[lo:hi] == part(a, lo + d, hi + d, 0xFFFFFFFF))))
                if (same[n:] - same[:-n] == n).any():
                    return True
                found = np.concatenate(([0], np.cumsum(band_grams(text, a, lo, hi, d, k))))
                run = n - Q + 1
                los = lo + np.flatnonzero(found[run:] - found[:-run] >= least)
                for i in range(0, len(los), BATCH):
                    if (band_distances(text, a, los[i : i + BATCH], n, d, k) <= k).any():
                        return True
        return False

    def items(self, a: np.ndarray) -> set[int]:
        x, found = self.x, set()
        g = grams(a, SEED)
        pos = np.flatnonzero(self.there[g >> np.uint64(64 - BITS)])
        if not len(pos) or not len(x.hash):
            return found
        left = np.searchsorted(x.hash, g[pos], "left")
        n = np.searchsorted(x.hash, g[pos], "right") - left
        pos, left, n = pos[n > 0], left[n > 0], n[n > 0]
        if not len(pos):
            return found
        # a repetitive item in a repetitive text has very many hits; so many places at a time that HITS bound them
        ends = np.cumsum(n)
        lo = 0
        while lo < len(n):
            hi = max(lo + 1, int(np.searchsorted(ends, (ends[lo - 1] if lo else 0) + HITS, "right")))
            m = n[lo:hi]
            p = np.repeat(pos[lo:hi], m)
            e = np.repeat(left[lo:hi] - np.concatenate(([0], np.cumsum(m)[:-1])), m) + np.arange(int(m.sum()))
            who, at = x.who[e], x.at[e]
            for item in np.unique(who).tolist():
                mine = who == item
                if x.ids[item] not in found and self.confirm(a, item, p[mine].astype(np.int64), at[mine].astype(np.int64)):
                    found.add(x.ids[item])
            lo = hi
        return found

    def alone(self, text: str) -> set[int]:
        """Short items that are a whole line of the text, or all of it."""
        found: set[int] = set()
        for line in (text, *text.split("\n")):
            found.update(self.x.short.get(normal(line, self.table).tobytes(), ()))
        return found

    def of(self, text: str | None) -> set[int]:
        found = self.alone(text or "") if self.x.short else set()
        a = normal(text, self.table)
        if len(a) <= PIECE:
            return found | self.items(a)
        over = 2 * WHOLE
        return found.union(*(self.items(a[i : i + PIECE + over]) for i in range(0, len(a), PIECE)))


def item_blocks(bench: DataFrame, item_col: str, text_col: str) -> Iterator[list[tuple[int, str]]]:
    """The items in lists of at most ITEM_BLOCK characters each, read one list at a time, in the order of a hash."""
    rows = bench.where(F.col(item_col).isNotNull() & F.col(text_col).isNotNull()).select(F.col(item_col).cast("long").alias("i"), F.col(text_col).alias("t")).distinct()
    size = rows.agg(F.coalesce(F.sum(F.char_length("t")), F.lit(0))).first()[0]
    n = -(-2 * size // ITEM_BLOCK)
    now, length, longest = [], 0, max(ITEM_BLOCK, 4 * WHOLE)
    for k in range(n):
        for r in rows.where(F.pmod(F.xxhash64("i", "t"), F.lit(n)) == k).toLocalIterator():
            for at in range(0, max(1, len(r.t) - 2 * WHOLE), longest - 2 * WHOLE):
                piece = r.t[at : at + longest]
                if now and length + len(piece) > ITEM_BLOCK:
                    yield now
                    now, length = [], 0
                now.append((r.i, piece))
                length += len(piece)
    if now:
        yield now


def scan(docs: DataFrame, items: list[tuple[int, str]], text_col: str, out: str) -> DataFrame:
    """Add ``out``: the sorted ids of the items that the text holds."""
    shared = docs.sparkSession.sparkContext.broadcast(ItemIndex(items))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        finder = Finder(shared.value)
        for batch in batches:
            found = [sorted(finder.of(t.as_py())) for t in batch.column(text_col)]
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(found, pa.list_(pa.int64()))], names=[*batch.schema.names, out])

    schema = f"{', '.join(f'`{f.name}` {f.dataType.simpleString()}' for f in docs.schema)}, `{out}` array<bigint>"
    return docs.mapInArrow(run, schema)


def leaks(docs: DataFrame, bench: DataFrame, text_col: str = "text", item_col: str = "item_id", item_text: str = "text", out: str = "leaked_items") -> DataFrame:
    """``docs`` with ``out``: the sorted ids of all benchmark items a text holds."""
    out, own, merged = free_name(docs.columns, out), docs.columns, None
    for items in item_blocks(bench, item_col, item_text):
        name = free_name(docs.columns, "held")
        docs = scan(docs, items, text_col, name)
        merged = F.col(name) if merged is None else F.array_sort(F.array_union(merged, F.col(name)))
    return docs.select(*[F.col(f"`{c}`") for c in own], (merged if merged is not None else F.array().cast("array<bigint>")).alias(out))


def clean(docs: DataFrame, bench: DataFrame, text_col: str = "text", item_col: str = "item_id", item_text: str = "text") -> DataFrame:
    """The documents that hold no benchmark item, their columns unchanged."""
    flag = free_name(docs.columns, "leaked_items")
    return leaks(docs, bench, text_col, item_col, item_text, flag).where(F.size(F.col(f"`{flag}`")) == 0).select(*[F.col(f"`{c}`") for c in docs.columns])
