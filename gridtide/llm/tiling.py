"""Benchmark decontamination by greedy string tiling.

Documents and benchmark items become token sequences.  Hashed seeds of
``MIN_MATCH`` tokens are joined, and an item whose shared seeds can't cover
enough of it is out.  For the others the longest run of free tokens that document
and item share is found by Karp-Rabin hashes of runs of one length, the length
by bisection, and marked as a tile; this is repeated until no run of
``MIN_MATCH`` is left.  An item whose tiles cover enough of its tokens, in
whatever order the document has them, marks the document.

Memory follows the lengths of a text and an item, never the number of pairs of
equal seeds, so junk that repeats one token costs no more than prose.

Defined cases: null, empty and blank texts match nothing; an item with fewer
than ``MIN_MATCH`` tokens can't be told from chance and matches nothing; a text
of any length is searched whole; rows that repeat are reported alike, once for
each row; further columns, whatever their names, are not read; empty tables give
no rows.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import kernel as K

MIN_MATCH = 5
COVERAGE = 0.6
SLICE_BYTES = 32 << 20  # benchmark text that is sent to the tasks at once
FOUND = "doc_id long, item_id long, coverage double, tiles long, matched_tokens long"

_ALNUM = np.zeros(256, bool)
_ALNUM[np.frombuffer(b"abcdefghijklmnopqrstuvwxyzABCDEFGHIJKLMNOPQRSTUVWXYZ0123456789", np.uint8)] = True


def token_words(column: pa.Array) -> tuple[K.Texts, K.Words]:
    """Tokens of lower-cased texts: runs of letters, marks and digits of any script."""
    texts = K.Texts(column, lower=True)
    return texts, K.Words(texts, True, _ALNUM, K.LETTERS | K.DIGITS)


def token_hashes(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """(token hashes, first token of each text)."""
    _, words = token_words(column)
    return words.hashes(), words.first


class PrefixHashes:
    """Karp-Rabin hashes of any runs of a token sequence, in constant time each."""

    def __init__(self, tokens: np.ndarray):
        up, self.down = K.powers(len(tokens))
        self.sums = np.concatenate([np.zeros(1, np.uint64), np.cumsum(tokens * up[: len(tokens)])])

    def runs(self, at: np.ndarray, size: int) -> np.ndarray:
        return (self.sums[at + size] - self.sums[at]) * self.down[at]


def _room(at: np.ndarray) -> np.ndarray:
    """Longest run that can start at each seed: to the end of the seeds that follow one another."""
    last = np.append(np.diff(at) != 1, True)
    stops = np.flatnonzero(last)
    return at[stops][np.searchsorted(stops, np.arange(len(at)))] - at + MIN_MATCH


def _free(at: np.ndarray, room: np.ndarray, start: int, size: int) -> tuple[np.ndarray, np.ndarray]:
    """Seeds and their room once a tile at ``start`` has taken its tokens."""
    room = np.where(at < start, np.minimum(room, start - at), room)
    keep = ((at < start) | (at >= start + size)) & (room >= MIN_MATCH)
    return at[keep], room[keep]


def tile(doc: np.ndarray, item: np.ndarray, doc_at: np.ndarray, item_at: np.ndarray, prefix: PrefixHashes | None = None) -> list[tuple[int, int, int]]:
    """Greedy tiles (document position, item position, length) from the sorted seed positions of both.

    The longest goes first, ties by item and then document position; no token
    lies in two tiles.
    """
    a, b = prefix or PrefixHashes(doc), PrefixHashes(item)
    room, item_room = _room(doc_at), _room(item_at)
    tiles, most = [], len(item)

    def starts(size: int):
        i, j = doc_at[room >= size], item_at[item_room >= size]
        return i, j, a.runs(i, size), b.runs(j, size)

    def shared(size: int) -> bool:
        _, _, x, y = starts(size)
        return bool(len(x) and len(y) and np.isin(y, x).any())

    while len(doc_at) and len(item_at):
        most = int(min(most, room.max(), item_room.max()))
        low, high = MIN_MATCH - 1, most + 1  # a shared run of ``low`` exists, none of ``high``
        probe = most
        while high - low > 1:
            low, high = (probe, high) if shared(probe) else (low, probe)
            probe = (low + high) // 2
        if low < MIN_MATCH:
            break
        i, j, x, y = starts(low)
        hit = None
        for k in np.flatnonzero(np.isin(y, x)).tolist():
            for spot in i[x == y[k]].tolist():
                if np.array_equal(doc[spot : spot + low], item[j[k] : j[k] + low]):
                    hit = spot, int(j[k])
                    break
            if hit:
                break
        if hit is None:  # equal hashes of different runs only
            most = low - 1
            if most < MIN_MATCH:
                break
            continue
        most = low
        tiles.append((*hit, low))
        doc_at, room = _free(doc_at, room, hit[0], low)
        item_at, item_room = _free(item_at, item_room, hit[1], low)
    return tiles


class Seeds:
    """Seed index of a bounded slice of the benchmark."""

    def __init__(self, ids: list, texts: list):
        hashes, first = token_hashes(pa.array(texts, pa.string()))
        self.ids = ids
        self.items = [hashes[a:b] for a, b in zip(first[:-1], first[1:], strict=True)]
        self.sizes = np.array([len(x) for x in self.items], np.int64)
        seeds, owner, at = [], [], []
        for k, item in enumerate(self.items):
            own = K.chained(item, MIN_MATCH)
            seeds.append(own)
            owner.append(np.full(len(own), k))
            at.append(np.arange(len(own)))
        seeds, owner, at = (np.concatenate(x) if x else np.zeros(0, np.int64) for x in (seeds, owner, at))
        order = np.argsort(seeds, kind="stable")
        seeds, self.owner, self.at = seeds[order].astype(np.uint64), owner[order], at[order]
        keys, starts = np.unique(seeds, return_index=True)
        self.starts = np.append(starts, len(seeds))
        self.lookup = K.HashLookup({int(k): i for i, k in enumerate(keys)})

    def _postings(self, groups: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(item, position, group) of every item seed in distinct groups, by item and position."""
        counts = self.starts[groups + 1] - self.starts[groups]
        pick = np.repeat(self.starts[groups], counts) + np.arange(counts.sum()) - np.repeat(np.cumsum(counts) - counts, counts)
        order = np.lexsort((self.at[pick], self.owner[pick]))
        return self.owner[pick][order], self.at[pick][order], np.repeat(groups, counts)[order]

    def search(self, hashes: np.ndarray, first: np.ndarray, least: float = 0.0):
        """(text, item, coverage, tiles, tokens) for every text and item that share a seed and may reach ``least`` coverage."""
        where, group = self.lookup.find(K.chained(hashes, MIN_MATCH))
        text = np.searchsorted(first, where, side="right") - 1
        inside = where + MIN_MATCH <= first[np.minimum(text + 1, len(first) - 1)]
        where, group, text = where[inside], group[inside], text[inside]
        cuts = np.append(np.flatnonzero(np.diff(text, prepend=-1)), len(text)).tolist()
        for low, high in zip(cuts[:-1], cuts[1:], strict=True):
            t = int(text[low])
            spots, groups = where[low:high] - first[t], group[low:high]
            owner, at, of = self._postings(np.unique(groups))
            starts = np.flatnonzero(np.diff(owner, prepend=-1))
            # tokens that seeds reach in an item bound what tiles can cover
            step = np.minimum(MIN_MATCH, np.append(np.diff(at), MIN_MATCH))
            stops = np.append(starts[1:], len(owner))
            step[stops - 1] = MIN_MATCH
            reach = np.add.reduceat(step, starts)
            doc, prefix = hashes[first[t] : first[t + 1]], None
            for s, e, most in zip(starts.tolist(), stops.tolist(), reach.tolist(), strict=True):
                k = int(owner[s])
                if most < least * self.sizes[k]:
                    continue
                prefix = prefix or PrefixHashes(doc)
                tiles = tile(doc, self.items[k], spots[np.isin(groups, of[s:e])], at[s:e], prefix)
                covered = sum(n for _, _, n in tiles)
                yield t, self.ids[k], covered / int(self.sizes[k]), len(tiles), covered


def _search(seeds: Seeds, least: float):
    def run(batches):
        for batch in K.chunks(batches, "text"):
            hashes, first = token_hashes(batch.column(1))
            rows = [(batch.column(0)[t].as_py(), *rest) for t, *rest in seeds.search(hashes, first, least) if rest[1] >= least]
            cols = list(zip(*rows, strict=True)) if rows else [()] * 5
            kinds = (pa.int64(), pa.int64(), pa.float64(), pa.int64(), pa.int64())
            yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(cols, kinds, strict=True)], names=[f.split()[0] for f in FOUND.split(", ")])

    return run


def contamination(documents: DataFrame, benchmark: DataFrame, least: float = COVERAGE) -> DataFrame:
    """(doc_id, item_id, coverage, tiles, matched_tokens) of each document and item with enough coverage.

    The benchmark goes to the tasks in slices of a checked size; one larger than
    a slice is worked through slice by slice.
    """
    docs = documents.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    items = benchmark.select(F.col("item_id").cast("long").alias("item_id"), F.col("text").cast("string").alias("text")).where("text is not null")
    size = items.agg(F.sum(F.octet_length("text").cast("long"))).first()[0] or 0
    slices = size // SLICE_BYTES + 1
    out = None
    for k in range(slices):
        part = items if slices == 1 else items.where(F.pmod(F.xxhash64("item_id", "text"), F.lit(slices)) == k)
        rows = sorted(part.collect(), key=lambda r: (r.item_id is None, r.item_id or 0, r.text))  # about SLICE_BYTES
        seeds = Seeds([r.item_id for r in rows], [r.text for r in rows])
        found = docs.mapInArrow(_search(seeds, least), FOUND)
        out = found if out is None else out.unionByName(found)
    return out


def op7_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Documents that hold a benchmark passage, with the item and its coverage."""
    return contamination(spark.read.parquet(f"{sf_dir}/documents.parquet"), spark.read.parquet(f"{sf_dir}/benchmark.parquet"))
