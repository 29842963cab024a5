"""N-gram Jaccard join by PartEnum signatures.

Texts become sets of hashed word n-grams.  Sizes fall into bands, each ending where
no set can match the band's least any more, so a match lies in one band or in two
neighbours; each band with the next is a class, in which matching sets differ in at
most ``k`` features.  On two levels the hash domain of a class is cut into ``n``
parts and each part into ``SUBPARTS`` subparts.  With ``n`` above ``k / 2`` some part
holds one difference at most, and then all of its subparts but one agree: every
subset of SUBPARTS - 1 subparts is enumerated, and the set's projection on it is a
signature.  A subset that holds nothing of a set proves nothing and is skipped; a
set with so many parts of that kind that all the agreeing ones might be among them
adds a further, independently cut scheme, until one has few enough (a pair is certain
to meet in the first scheme that either of the two passes).  The join therefore
loses no pair.  Features are 64-bit hashes of n-grams: two different n-grams count as
one with a probability of 2 ** -64.

Sets that share a signature are candidates.  They are compared exactly, first
with the least member of their signature group (a star, never all pairs), then
only those pairs whose link is still open: members of different components.
These come in rings: a set outside its group's main component meets a few members
first, and ever more of them only while it is in a component of its own, so that
pairs which later merges make needless are never listed.  The last ring leaves no
member out.  That settles components.  Links themselves are asked for separately: every link
lies inside a component, so all pairs of a component's sets are then compared,
in blocks, and each row's number of links is exact.
Before any comparison parity sketches, of 512 bits first and then of at least a
bit for each item, bound the difference of two sets from below, exactly, and
drop pairs that cannot reach the similarity.
"""

from __future__ import annotations

from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import kernel as K
from .components import connected
from .store import Scratch, partitions

N_WORDS = 5
NUM, DEN = 80, 100  # similarity as a fraction
SIG_BYTES, SET_BYTES = 6, 6
SEEN_MOST = 1 << 18
SUBPARTS = 3  # subparts of a part; all subsets of one less are enumerated
CHUNK = 4096  # members of a signature group in one cell at most, about
MEET, WIDER = 32, 16  # members of its largest group that a set meets in the first ring, and each ring's end over that of the one before
CIRCLE = 30  # bits of a set's place on the circle along which rings are cut
MOST_SCHEMES = 64
SKETCH = 8  # longs of a parity sketch
NEED_MOST = 1 << 18  # ids that are broadcast at most
LONGS = [f"s{i}" for i in range(SKETCH)]
BLOCK, BLOCK_ITEMS = 256, 1 << 20  # sets, and their items, in one block of a component
SLICE_CELLS = 1 << 21  # cells of a dense slice when a block is compared


def distinct_shingles(hashes: np.ndarray, n: int = N_WORDS) -> np.ndarray:
    """Sorted distinct n-gram hashes of one text's word hashes."""
    if not len(hashes):
        return np.zeros(0, np.uint64)
    return np.unique(K.chained(hashes, min(n, len(hashes))))


def text_sets(texts: K.Texts, n: int = N_WORDS):
    """One sorted hash set for each text of a batch."""
    words = K.Words(texts)
    hashes = words.hashes()
    grams = K.chained(hashes, n)
    for a, b in zip(words.first[:-1], words.first[1:], strict=True):
        yield np.unique(grams[a : b - n + 1]) if b - a >= n else distinct_shingles(hashes[a:b], n)


def set_key(items: np.ndarray) -> tuple[int, int]:
    """Two independent 64-bit digests of a set."""
    return (
        int(np.bitwise_xor.reduce(K.mix(items + K.STEP))) if len(items) else 0,
        int(K.mix(items ^ np.uint64(0x5851F42D4C957F2D)).sum(dtype=np.uint64)) if len(items) else 0,
    )


@lru_cache(maxsize=None)
def _parts(k: int, least: int) -> int:
    """Fewest parts for which a set of ``least`` items usually has few with all items in one subpart, or none."""
    best, at = -np.inf, k // 2 + 1
    parts = at
    while parts <= 4 * (k // 2 + 1):
        load = least / parts
        poor = parts * (SUBPARTS * np.exp(-load * (SUBPARTS - 1) / SUBPARTS) - (SUBPARTS - 1) * np.exp(-load))
        margin = (parts - k // 2 - 1 - poor) / np.sqrt(poor + 1e-9)
        if margin > best:
            best, at = margin, parts
        if margin >= 0.5:
            break
        parts += max(1, parts // 64)
    return at


@lru_cache(maxsize=None)
def bands(size: int) -> tuple[tuple[int, int, int], ...]:
    """(number, least size, largest size) of the band of a set size and of the band before it."""
    low, number, before = 1, 0, None
    while True:
        high = low * DEN // NUM
        if low <= size <= high:
            return ((number, low, high),) if before is None else (before, (number, low, high))
        before, low, number = (number, low, high), high + 1, number + 1


@lru_cache(maxsize=None)
def classes(size: int) -> tuple[tuple[int, int, int], ...]:
    """(class, differing features at most, parts) of each class of a set size.

    Class i is for pairs whose smaller set lies in band i: |x ^ y| is at most
    (|x| + |y|) * (1 - t) / (1 + t), and the larger set has |x| / t items at most.
    """
    out = []
    for number, low, high in bands(size):
        top = high * DEN // NUM
        if size <= top:
            k = (high + top) * (DEN - NUM) // (DEN + NUM)
            out.append((number, k, _parts(k, low)))
    return tuple(out)


def signatures(items: np.ndarray) -> np.ndarray:
    """All PartEnum signatures of one sorted set."""
    out = []
    for cls, k, parts in classes(len(items)):
        if not k:  # only equal sets match
            out.append(K.mix(K.mix(items + K.STEP).sum(dtype=np.uint64, keepdims=True) ^ np.uint64((cls + 1) * K.BASE & K.MASK)))
            continue
        # both levels are cut into equal ranges of the hash's upper 32 bits
        edges = (np.arange(parts * SUBPARTS + 1, dtype=np.uint64) << np.uint64(32)) // np.uint64(parts * SUBPARTS)
        for scheme in range(MOST_SCHEMES):
            salt = np.uint64(scheme * K.BASE & K.MASK)
            view = items if not scheme else np.sort(K.mix(items ^ salt))
            cuts = np.searchsorted(view >> np.uint64(32), edges)
            sums = np.concatenate([np.zeros(1, np.uint64), np.cumsum(K.mix(view + K.STEP))])
            part = K.mix((sums[cuts[1:]] - sums[cuts[:-1]]) ^ K.STEP).reshape(parts, SUBPARTS)
            held = (np.diff(cuts) > 0).reshape(parts, SUBPARTS)
            passed = int((held.sum(axis=1) < 2).sum()) < parts - k // 2
            whole = part.sum(axis=1, dtype=np.uint64)
            for left in range(SUBPARTS):  # the subset of all subparts but this one
                some = held.sum(axis=1) > held[:, left]
                full = np.flatnonzero(some) if passed or scheme < MOST_SCHEMES - 1 else np.arange(parts)
                label = np.uint64(((cls + 1) << 32 | scheme << 20 | left << 16) * K.BASE & K.MASK)
                out.append(K.mix((whole[full] - part[full, left]) ^ K.mix(full.astype(np.uint64) * K.STEP + label)))
            if passed:
                break
    return np.concatenate(out)


def parity_sketch(items: np.ndarray) -> np.ndarray:
    """Bit j is the parity of the items that fall on j; sketches of two sets differ in no more bits than the sets in items.

    The width is a power of two, 64 * SKETCH bits at least and no less than the
    set's size; folding halves onto each other gives the sketch of half the width.
    """
    width = max(64 * SKETCH, 1 << (max(1, len(items)) - 1).bit_length())
    at = K.mix(items ^ np.uint64(0xA0761D6478BD642F)) & np.uint64(width - 1)
    return np.packbits((np.bincount(at.astype(np.int64), minlength=width) & 1).astype(np.uint8)).view(np.uint64)


def folded(sketch: np.ndarray, longs: int) -> np.ndarray:
    return np.bitwise_xor.reduce(sketch.reshape(-1, longs), axis=0)


def _describe(batches):
    for batch in K.chunks(batches, "text"):
        sizes, ones, twos, bits, wide = [], [], [], [], []
        for items in text_sets(K.Texts(batch.column(1))):
            one, two = set_key(items)
            sizes.append(len(items))
            ones.append(one)
            twos.append(two)
            whole = parity_sketch(items)
            bits.append(folded(whole, SKETCH))
            wide.append(whole.tobytes())
        bits = np.array(bits)
        yield pa.RecordBatch.from_arrays(
            [batch.column(0), pa.array(sizes, pa.int64()), *(K.long_array(np.array(x, np.uint64)) for x in (ones, twos)), *(K.long_array(bits[:, i]) for i in range(SKETCH)), pa.array(wide, pa.binary())],
            names=["doc_id", "n", "h1", "h2", *LONGS, "wide"],
        )


def _emit(buckets: int):
    """Signature entries of a task, gathered by bucket; a set seen before in the task adds none."""

    def run(batches):
        seen: set = set()
        for batch in K.chunks(batches, "text"):
            ids = np.asarray(batch.column(0).fill_null(-1), np.int64).view(np.uint64)
            sigs, docs, keys = [], [], []
            for i, items in enumerate(text_sets(K.Texts(batch.column(1)))):
                if not len(items) or batch.column(0)[i].as_py() is None:
                    continue
                key = set_key(items)
                if key in seen:
                    continue
                if len(seen) >= SEEN_MOST:
                    seen.clear()
                seen.add(key)
                own = np.unique(signatures(items))
                sigs.append(own)
                docs.append(np.full(len(own), ids[i]))
                keys.append(np.full(len(own), np.uint64(key[0])))
            if not sigs:
                continue
            sig, doc, key = np.concatenate(sigs), np.concatenate(docs), np.concatenate(keys)
            bucket = ((sig >> np.uint64(40)) * np.uint64(buckets)) >> np.uint64(24)
            order = np.argsort(bucket, kind="stable")
            sig, doc, key, bucket = sig[order], doc[order], key[order], bucket[order]
            heads = np.flatnonzero(np.diff(bucket, prepend=np.uint64(buckets + 1)))
            cuts = np.append(heads, len(bucket))
            blob = [[], [], []]
            for a, b in zip(cuts[:-1], cuts[1:], strict=True):
                blob[0].append(K.packed(sig[a:b], SIG_BYTES))
                blob[1].append(K.packed(doc[a:b], 8))
                blob[2].append(K.packed(key[a:b], SET_BYTES))
            yield pa.RecordBatch.from_arrays(
                [pa.array(bucket[heads].astype(np.int32)), *(pa.array(x, pa.binary()) for x in blob)],
                names=["bucket", "sigs", "docs", "sets"],
            )

    return run


def _shared(batches):
    """Entries whose signature is held by two different sets at least, of one task's buckets."""
    held: dict[int, list] = {}
    for batch in batches:
        for bucket, *blobs in zip(*(batch.column(i).to_pylist() for i in range(4)), strict=True):
            held.setdefault(bucket, []).append(blobs)
    for bucket in list(held):
        blobs = held.pop(bucket)
        sig, doc, key = (
            np.concatenate([K.unpacked(x[i], w) for x in blobs]) for i, w in enumerate((SIG_BYTES, 8, SET_BYTES))
        )
        order = np.lexsort((doc, key, sig))
        sig, doc, key = sig[order], doc[order], key[order]
        new_sig = np.append(True, sig[1:] != sig[:-1])
        first = new_sig | np.append(True, key[1:] != key[:-1])  # one entry for each set of a group
        sig, doc, new_sig = sig[first], doc[first], new_sig[first]
        group = np.cumsum(new_sig) - 1
        many = np.bincount(group)[group] > 1
        if many.any():
            yield pa.RecordBatch.from_arrays(
                [K.long_array(sig[many] ^ np.uint64(bucket << 48 & K.MASK)), K.long_array(doc[many])], names=["sig", "doc"]
            )


def _sets(batches):
    for batch in K.chunks(batches, "text"):
        yield pa.RecordBatch.from_arrays(
            [batch.column(0), pa.array([x.tobytes() for x in text_sets(K.Texts(batch.column(1)))], pa.binary())],
            names=["doc", "items"],
        )


def _overlaps(batches):
    for batch in batches:
        both = [np.array([np.intersect1d(np.frombuffer(a, np.uint64), np.frombuffer(b, np.uint64), True).size, len(a) // 8, len(b) // 8]) for a, b in zip(batch.column(2).to_pylist(), batch.column(3).to_pylist(), strict=True)]
        both = np.array(both, np.int64).reshape(-1, 3)
        yield pa.RecordBatch.from_arrays(
            [batch.column(0), batch.column(1), pa.array(both[:, 0]), pa.array(both[:, 1] + both[:, 2] - both[:, 0])],
            names=["a", "b", "common", "joint"],
        )


def _block_links(owner_block: np.ndarray, weight: np.ndarray, items: list[np.ndarray], i: int, j: int) -> np.ndarray:
    """Links of each set of a cell to the sets of its other block, each counted with its weight."""
    x, y = np.flatnonzero(owner_block == i), np.flatnonzero(owner_block == j)
    size = np.array([len(v) for v in items], np.int64)
    owner = np.repeat(np.arange(len(items)), size)
    order = np.argsort(np.concatenate(items), kind="stable")
    value, owner = np.concatenate(items)[order], owner[order]
    column = np.cumsum(np.append(False, value[1:] != value[:-1]))
    held = np.bincount(column)[column] > 1  # items of one set only are common to none
    _, column = np.unique(column[held], return_inverse=True)
    owner = owner[held]
    common = np.zeros((len(x), len(y)), np.int64)
    width = max(1, SLICE_CELLS // len(items))
    for low in range(0, int(column[-1]) + 1 if len(column) else 0, width):
        a, b = np.searchsorted(column, [low, low + width])
        dense = np.zeros((len(items), width), np.float32)
        dense[owner[a:b], column[a:b] - low] = 1
        common += (dense[x] @ dense[y].T).astype(np.int64)  # exact: a slice has under 2 ** 24 columns
    linked = common * DEN >= (size[x][:, None] + size[y][None, :] - common) * NUM
    out = np.zeros(len(items), np.int64)
    if i == j:
        np.fill_diagonal(linked, False)
        out[x] = linked @ weight[y]
    else:
        out[x], out[y] = linked @ weight[y], weight[x] @ linked
    return out


def _cell_links(batches):
    """Links that each cell (root, i, j) adds to its sets; rows come sorted by cell."""
    key, held = None, []

    def done():
        rep, block, weight, items = zip(*held, strict=True)
        links = _block_links(np.array(block), np.array(weight, np.int64), list(items), key[1], key[2])
        return pa.RecordBatch.from_arrays([pa.array(rep, pa.int64()), pa.array(links)], names=["rep", "links"])

    for batch in batches:
        for root, i, j, rep, block, weight, items in zip(*(c.to_pylist() for c in batch.columns), strict=True):
            if (root, i, j) != key:
                if held:
                    yield done()
                key, held = (root, i, j), []
            held.append((rep, block, weight, np.frombuffer(items, np.uint64)))
    if held:
        yield done()


class NgramJaccardJoin:
    """Exact similarity self-join of texts at a Jaccard similarity of 0.8 over 5-word shingles."""

    def __init__(self, spark: SparkSession, scratch: Scratch | None = None):
        self.spark = spark
        self.scratch = scratch or Scratch(spark, "jaccard")

    def _verify(self, docs: DataFrame, pairs: DataFrame, tag: str) -> DataFrame:
        """(a, b, common, joint) of each pair, from the whole sets of both texts."""
        need = pairs.select(F.col("a").alias("doc_id")).unionByName(pairs.select(F.col("b").alias("doc_id"))).distinct()
        need = self.scratch.keep(need, f"{tag}-need")
        few = need.count() <= NEED_MOST
        some = docs.join(F.broadcast(need) if few else need, "doc_id", "left_semi").select("doc_id", "text")
        sets = self.scratch.keep(some.mapInArrow(_sets, "doc long, items binary").dropDuplicates(["doc"]), f"{tag}-sets")
        left = pairs.join(sets.select(F.col("doc").alias("a"), F.col("items").alias("x")), "a")
        both = left.join(sets.select(F.col("doc").alias("b"), F.col("items").alias("y")), "b").select("a", "b", "x", "y")
        done = self.scratch.keep(both.mapInArrow(K.trimming(_overlaps), "a long, b long, common long, joint long"), tag)
        self.scratch.drop(f"{tag}-sets", f"{tag}-need")
        return done

    def run(self, documents: DataFrame, links: bool = False) -> DataFrame:
        """(doc_id, n_shingles, component_id) for every row of ``documents``, with ``n_links`` where ``links`` are asked for.

        ``n_links`` is the number of other ids whose set is similar to the
        row's, those of equal sets included.  Null and blank texts have an
        empty set and are linked with nothing; rows without an id stand alone
        with a null component and no links.
        """
        keep, scratch = self.scratch.keep, self.scratch
        docs = documents.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
        info = keep(docs.mapInArrow(_describe, "doc_id long, n long, h1 long, h2 long, " + ", ".join(f"{x} long" for x in LONGS) + ", wide binary"), "info")
        wide = info.where("n > 0 and doc_id is not null").groupBy("n", "h1", "h2").agg(F.min("doc_id").alias("rep"))
        wide = keep(wide, "classes")  # written, so that a join with a large class can be split
        total = info.agg(F.sum("n")).first()[0] or 0
        parts = max(partitions(self.spark), total // 3_000_000)
        buckets = int(min(1 << 23, parts * 8))
        entries = (
            docs.mapInArrow(_emit(buckets), "bucket int, sigs binary, docs binary, sets binary")
            .repartition(parts, "bucket")
            .mapInArrow(K.trimming(_shared), "sig long, doc long")
        )
        reps = info.join(wide, ["n", "h1", "h2"]).select(F.col("doc_id").alias("doc"), "rep")
        entries = keep(entries, "shared")
        # an id stands for its set's least id, so copies in other tasks fall together
        entries = keep(entries.join(reps, "doc").select("sig", F.col("rep").alias("doc")).distinct(), "entries")
        scratch.drop("shared")
        heads = entries.groupBy("sig").agg(F.min("doc").alias("lead"))
        starred = keep(entries.join(keep(heads, "heads"), "sig"), "starred")
        scratch.drop("entries", "heads")
        wanted = starred.select(F.col("doc").alias("doc_id")).distinct()
        sketch = info.join(wanted, "doc_id", "left_semi").select(F.col("doc_id").alias("doc"), "n", *LONGS, "wide").dropDuplicates(["doc"])
        sketch = keep(sketch, "sketch")
        # each set first meets the least of its leaders
        first = starred.where("doc <> lead").groupBy("doc").agg(F.min("lead").alias("a")).select("a", F.col("doc").alias("b"))
        checked, turn, low, high, most = None, 0, 0, MEET, 0
        while turn < 2 or low < most:
            pairs = first if turn == 0 else self._leader_pairs(starred, labels, checked, sketch) if turn == 1 else self._cross_pairs(live, checked, sketch, low, high)
            pairs = keep(_possible(pairs, sketch), f"open-{turn}")
            met = turn < 2 or not pairs.isEmpty()
            if met:
                done = self._verify(docs, pairs, f"round-{turn}")
                checked = done if checked is None else checked.unionByName(done)
                near = checked.where(F.col("common") * DEN >= F.col("joint") * NUM)
                labels = connected(near.select(F.col("b").alias("u"), F.col("a").alias("v")), scratch, f"label-{turn}")
            scratch.drop(f"open-{turn}")
            turn += 1
            if turn == 2:
                live = self._apart(starred, labels)
            elif turn > 2:
                low, high = high, high * WIDER
                if met and low < most:
                    live = keep(self._mixed(live, labels, turn, low), f"live-{turn}")
            if turn > 1:  # where low reaches the largest group of all that are left, every pair across components has been met
                most = live.agg(F.max("most")).first()[0] or 0
        # the result reads sets, classes and labels; all else can go
        scratch.drop("sketch", "starred", "shape", "apart", *(f"{t}-{k}" for t in ("live", "mixed") for k in range(1, turn + 1)))
        label = labels.select(F.col("node").alias("rep"), "root")
        shown = ["doc_id", F.col("n").alias("n_shingles"), F.coalesce("root", "rep", "doc_id").alias("component_id")]
        if links:  # joined to classes, not rows, so that a large class is no hot key
            wide = keep(wide.join(self._degrees(docs, info, wide, label), "rep", "left"), "degrees")
            known = F.col("doc_id").isNotNull() & F.col("n_links").isNotNull()
            shown.append(F.when(known, F.col("n_links")).otherwise(0).alias("n_links"))
        found = info.join(wide, ["n", "h1", "h2"], "left").join(label, "rep", "left")
        return found.select(*shown)

    def _degrees(self, docs: DataFrame, info: DataFrame, wide: DataFrame, label: DataFrame) -> DataFrame:
        """(rep, n_links) of each class of equal sets: the ids in it but one, and those of all similar sets.

        A component's sets are dealt to blocks, and each pair of blocks is a
        cell of its own, so a large component is worked on by many tasks.
        """
        keep, scratch = self.scratch.keep, self.scratch
        ids = info.where("n > 0 and doc_id is not null").select("doc_id", "n", "h1", "h2").distinct()
        size = ids.groupBy("n", "h1", "h2").agg(F.count("*").alias("weight"))
        size = keep(size.join(wide, ["n", "h1", "h2"]).select("rep", "n", "weight"), "sizes")
        members = keep(size.join(label, "rep"), "members")
        blocks = members.groupBy("root").agg(F.greatest(F.ceil(F.count("*") / BLOCK), F.ceil(F.sum("n") / BLOCK_ITEMS)).cast("int").alias("blocks"))
        blocks = keep(blocks, "blocks")
        members = members.join(blocks, "root").select("rep", "root", "weight", "blocks", F.pmod(F.xxhash64("rep"), F.col("blocks")).cast("int").alias("block"))
        need = keep(members.select(F.col("rep").alias("doc_id")), "links-need")
        some = docs.join(F.broadcast(need) if need.count() <= NEED_MOST else need, "doc_id", "left_semi").select("doc_id", "text")
        sets = keep(some.mapInArrow(_sets, "doc long, items binary").dropDuplicates(["doc"]), "links-sets")
        dealt = members.join(sets.withColumnRenamed("doc", "rep"), "rep").withColumn("other", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)))
        cells = dealt.select("root", F.least("block", "other").alias("i"), F.greatest("block", "other").alias("j"), "rep", "block", "weight", "items")
        cells = cells.repartition(partitions(self.spark), "root", "i", "j").sortWithinPartitions("root", "i", "j")
        similar = keep(cells.mapInArrow(K.trimming(_cell_links), "rep long, links long").groupBy("rep").agg(F.sum("links").alias("links")), "links")
        scratch.drop("members", "blocks", "links-need", "links-sets")
        return size.join(similar, "rep", "left").select("rep", (F.col("weight") - 1 + F.coalesce("links", F.lit(0))).alias("n_links"))

    def _mixed(self, groups: DataFrame, labels: DataFrame, turn: int, low: int = 0) -> DataFrame:
        """Members of signature groups that still hold several components, with their component; with ``low`` only of groups in which rings go on beyond it."""
        of = labels.select(F.col("node").alias("doc"), F.col("root").alias("comp"))
        held = groups.drop("comp").join(of, "doc", "left").withColumn("comp", F.coalesce("comp", "doc"))
        reach = F.max("most") if low else F.lit(1)
        mixed = held.groupBy("sig").agg(F.min("comp").alias("lo"), F.max("comp").alias("hi"), reach.alias("reach")).where(f"lo < hi and reach > {low}").select("sig")
        return held.join(self.scratch.keep(mixed, f"mixed-{turn}"), "sig")

    def _leader_pairs(self, starred: DataFrame, labels: DataFrame, checked: DataFrame, sketch: DataFrame) -> DataFrame:
        """Members that their signature's leader has not met and whose component differs."""
        live = self._mixed(starred, labels, 1)
        lead = labels.select(F.col("node").alias("lead"), F.col("root").alias("lead_comp"))
        live = live.where("doc <> lead").select("lead", "doc", "comp").distinct().join(lead, "lead", "left")
        pairs = live.where(F.coalesce("lead_comp", "lead") != F.col("comp")).select(F.col("lead").alias("a"), F.col("doc").alias("b"))
        return pairs.join(checked.select("a", "b"), ["a", "b"], "left_anti")

    def _apart(self, starred: DataFrame, labels: DataFrame) -> DataFrame:
        """Members of groups of several components; ``most``, the size of its largest such group, is null for a group's main component.

        Later merges may give a group another main component.  ``most`` and the
        group's size ``m`` stay, so that rings go on where they were.
        """
        live = self.scratch.keep(self._mixed(starred, labels, 2).select("sig", "doc", "comp"), "apart")
        by_comp = live.groupBy("sig", "comp").agg(F.count("*").alias("k"))
        shape = by_comp.groupBy("sig").agg(F.max_by("comp", F.struct("k", "comp")).alias("main"), F.sum("k").alias("m"))
        live = live.join(self.scratch.keep(shape, "shape"), "sig")
        most = live.where("comp <> main").groupBy("doc").agg(F.max("m").alias("most"))
        live = live.join(most, "doc", "left").withColumn("most", F.when(F.col("comp") != F.col("main"), F.col("most")))
        return self.scratch.keep(live.select("sig", "doc", "comp", "m", "most"), "live-2")

    def _cross_pairs(self, live: DataFrame, checked: DataFrame, sketch: DataFrame, low: int, high: int) -> DataFrame:
        """Pairs of a group across components that lie in one ring.

        All sets have a place on a circle.  A set outside a group's main
        component meets those members to which the way on is a share of the
        circle from ``low / most`` to ``high / most``, the same in all of its groups.
        """
        one = 1 << CIRCLE
        live = live.join(sketch.drop("wide"), "doc").withColumn("at", F.pmod(F.xxhash64("doc"), F.lit(one)))
        live = live.withColumn("cells", F.ceil(F.col("m") / min(high - low, CHUNK)))
        start, end = F.expr(f"{low * one}L div most"), F.least(F.expr(f"{high * one - 1}L div most"), F.lit(one - 1))
        start, end = (F.shiftright((F.col("at") + x) * F.col("cells"), CIRCLE) for x in (start, end))
        every = F.explode(F.sequence(start, F.least(end, start + F.col("cells") - 1)))
        names = ["doc", "comp", "n", "at", *LONGS]
        x = live.where(F.col("most") > low).select("sig", "cells", F.struct("most", *names).alias("x"), every.alias("cell"))
        x = x.select("sig", F.pmod("cell", "cells").alias("cell"), "x")
        y = live.select("sig", F.shiftright(F.col("at") * F.col("cells"), CIRCLE).alias("cell"), F.struct(*names).alias("y"))
        way = F.pmod(F.col("y.at") - F.col("x.at"), F.lit(one)) * F.col("x.most")
        may = (F.col("x.comp") != F.col("y.comp")) & (way >= low * one) & (way < high * one) & _close(F.col("x"), F.col("y"))
        pairs = x.join(y, ["sig", "cell"]).where(may).select(F.least("x.doc", "y.doc").alias("a"), F.greatest("x.doc", "y.doc").alias("b")).distinct()
        return pairs.join(checked.select("a", "b"), ["a", "b"], "left_anti")


def _close(x, y):
    """True unless sizes or sketches prove that two sets are too different."""
    bits = sum((F.bit_count(x[s].bitwiseXOR(y[s])) for s in LONGS), F.lit(0))
    sizes = F.least(x["n"], y["n"]) * DEN >= F.greatest(x["n"], y["n"]) * NUM
    return sizes & (bits * (DEN + NUM) <= (x["n"] + y["n"]) * (DEN - NUM))


def _possible(pairs: DataFrame, sketch: DataFrame) -> DataFrame:
    """Pairs (a, b) that :func:`_close` leaves."""
    whole = F.struct("n", *LONGS)
    x = sketch.select(F.col("doc").alias("a"), whole.alias("x"))
    y = sketch.select(F.col("doc").alias("b"), whole.alias("y"))
    left = pairs.join(x, "a").join(y, "b").where(_close(F.col("x"), F.col("y"))).select("a", "b")
    u = sketch.select(F.col("doc").alias("a"), F.col("n").alias("na"), F.col("wide").alias("u"))
    v = sketch.select(F.col("doc").alias("b"), F.col("n").alias("nb"), F.col("wide").alias("v"))
    both = left.join(u, "a").join(v, "b").select("a", "b", "na", "nb", "u", "v")
    return both.mapInArrow(K.trimming(_wide_close), "a long, b long")


def _wide_close(batches):
    for batch in batches:
        keep = []
        for na, nb, u, v in zip(*(batch.column(i).to_pylist() for i in range(2, 6)), strict=True):
            u, v = np.frombuffer(u, np.uint64), np.frombuffer(v, np.uint64)
            longs = min(len(u), len(v))
            bits = int(np.bitwise_count(folded(u, longs) ^ folded(v, longs)).sum())
            keep.append(bits * (DEN + NUM) <= (na + nb) * (DEN - NUM))
        yield batch.select(["a", "b"]).filter(pa.array(keep, pa.bool_()))


def op2_ngram_jaccard_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Components of the near-duplicate links among all documents."""
    return NgramJaccardJoin(spark).run(spark.read.parquet(f"{sf_dir}/documents.parquet"))


def ngram_jaccard_links(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The components of op2_ngram_jaccard_join, with each document's exact number of near-duplicate links."""
    return NgramJaccardJoin(spark).run(spark.read.parquet(f"{sf_dir}/documents.parquet"), links=True)


SQL = """
WITH RECURSIVE words AS (
  SELECT doc_id, list_filter(regexp_split_to_array(
    translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'),
    '[\\x20\\x09-\\x0D]+'), lambda x: x <> '') AS w
  FROM documents),
shingles AS (
  SELECT DISTINCT doc_id, unnest(CASE WHEN len(w) = 0 THEN [] WHEN len(w) < 5 THEN [array_to_string(w, ' ')]
    ELSE list_transform(range(1, len(w) - 3), lambda i: array_to_string(w[i:i + 4], ' ')) END) AS s
  FROM words),
sizes AS (SELECT doc_id, count(*) AS n FROM shingles GROUP BY doc_id),
common AS (
  SELECT x.doc_id AS a, y.doc_id AS b, count(*) AS c
  FROM shingles x JOIN shingles y ON x.s = y.s AND x.doc_id <> y.doc_id GROUP BY 1, 2),
links AS (
  SELECT a, b FROM common JOIN sizes p ON p.doc_id = a JOIN sizes q ON q.doc_id = b
  WHERE 100 * c >= 80 * (p.n + q.n - c)),
reach AS (
  SELECT doc_id AS a, doc_id AS b FROM documents
  UNION SELECT r.a, l.b FROM reach r JOIN links l ON r.b = l.a)
SELECT d.doc_id, CAST(coalesce(s.n, 0) AS BIGINT) AS n_shingles, m.component_id
FROM documents d LEFT JOIN sizes s USING (doc_id)
JOIN (SELECT a AS doc_id, min(b) AS component_id FROM reach GROUP BY a) m USING (doc_id)
"""

LINKS_SQL = f"""
WITH words AS (
  SELECT doc_id, list_filter(regexp_split_to_array(
    translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'),
    '[\\x20\\x09-\\x0D]+'), lambda x: x <> '') AS w
  FROM documents),
shingles AS (
  SELECT DISTINCT doc_id, unnest(CASE WHEN len(w) = 0 THEN [] WHEN len(w) < 5 THEN [array_to_string(w, ' ')]
    ELSE list_transform(range(1, len(w) - 3), lambda i: array_to_string(w[i:i + 4], ' ')) END) AS s
  FROM words),
sizes AS (SELECT doc_id, count(*) AS n FROM shingles GROUP BY doc_id),
links AS (
  SELECT x.doc_id AS a, y.doc_id AS b FROM shingles x JOIN shingles y ON x.s = y.s AND x.doc_id <> y.doc_id
  JOIN sizes p ON p.doc_id = x.doc_id JOIN sizes q ON q.doc_id = y.doc_id
  GROUP BY x.doc_id, y.doc_id, p.n, q.n HAVING 100 * count(*) >= 80 * (p.n + q.n - count(*)))
SELECT c.*, (SELECT count(*) FROM links WHERE a = c.doc_id) AS n_links FROM ({SQL}) c
"""
