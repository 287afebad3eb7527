"""Jaccard join of shingle sets: universe partition, pigeonhole signatures, exact checks.

Sets of a size band differ from a partner by at most H elements. The universe is cut into
segments; segment i gets a value v (0: the subset itself is a signature; 1: also every
subset with one element left out). If the v + 1 sum to H + 1, two similar sets share a
signature in some segment; if they sum to that and e times the largest v + 1 more, in e + 1
segments. How many segments get which value, and e, are decided by cost: rows emitted,
against the chance collisions expected for the table's size.

There are two partitions. The first leaves frequent elements out (those of a sample's
distinct sets that several hold; what they tell apart is little, and leaving elements out
of a universe only lowers differences). A set with at most e scarce segments there (no
element to tell it by) needs no signatures of empty subsets: of the e + 1 segments that it
shares with a partner, one has elements. Only the poor rest, mostly copies of frequent texts,
takes part in the second partition, of the whole universe. Two similar sets of which one is
not poor meet in the first, two poor ones in the second. Samples change costs, never results.

Sets that share a signature stand in one bucket; equal buckets are one. Inside a bucket each
pair is held against a bound that loses nothing: the parities of both sets' elements over a
bit field differ in at most as many bits as the sets do in elements. A set is first checked
exactly only against the least one that passes, and links that hold make classes. A second
round checks all passing pairs of different classes that were not tried, so that no link
between classes is lost, while a group of copies never yields all its pairs.

Shingles are compared by 64-bit hashes of their words' hashes, equal sets by 128 bits; no
words are compared (a false link needs hashes of different shingles of one pair to collide).

Defined results: a null or empty text has an empty set and is alone; fewer words than a
shingle make one shingle of all; equal sets are linked; a null doc_id is no node and gets a
null component; rows that repeat a doc_id are one node (in `set_classes` each row stands for
itself); ids may be of any type that has an order; an empty table gives none; other columns
of the input play no part.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import textkit as tk
from .common import WHITE, cut, discard, fresh_names, partitions, ship
from .components import components

#: Sets of a bucket that are compared in one task; a larger bucket is dealt into pairs of blocks.
BLOCK = 1024
#: Broadcast the ids to check only up to so many.
BROADCAST_IDS = 200_000
#: Set hashes that a task remembers, to send the signatures of equal sets once.
SEEN = 200_000
#: Documents of the sample that shows which elements are frequent, in how many sets of it, and how many are kept at most.
SAMPLE, FREQUENT, FREQUENT_ELEMENTS = 10_000, 3, 100_000
#: Scarce segments that a set may have by chance, and rows that a chance link is worth.
SCARCE_MEAN, LINK_COST = 0.3, 1000
#: Signatures that are packed or sorted at once, and parts of a partition.
PACKED, PARTS = 750_000, 8
#: Least bits of a parity field, and bits a element; words of a block of compared fields; pairs that a task holds; checks against one set in a task.
FIELD_BITS, ELEMENT_BITS, COMPARED_WORDS, FOUND_PAIRS, CHECKS = 512, 2, 1 << 21, 500_000, 512


def size_bands(longest: int, percent: int) -> np.ndarray:
    """Least size of each band; a similar partner lies in the same or the next band."""
    low = [1]
    while low[-1] <= longest:
        low.append(low[-1] * 100 // percent + 1)
    return np.array(low, dtype=np.int64)


def most_different(high: int, percent: int) -> int:
    """Largest symmetric difference of a set of at most `high` elements and a similar larger one."""
    return (100 - percent) * (high + high * 100 // percent) // (100 + percent)


def more_than(e: int, mean: float) -> float:
    """Chance that a Poisson number exceeds e."""
    term = total = math.exp(-mean)
    for k in range(1, e + 1):
        term *= mean / k
        total += term
    return max(0.0, 1.0 - total)


_allocated: dict[tuple[int, int, int], tuple[int, int, int]] = tk.Kept()


def allocate(size: int, h: int, n_docs: int) -> tuple[int, int, int]:
    """(segments with v = 0, segments with v = 1, e) of least cost for sets of about `size` elements.

    A document emits plain + one_out * (1 + elements of a segment) rows; by chance it meets
    the documents that are poor as well.
    """
    if (size, h, n_docs) in _allocated:
        return _allocated[size, h, n_docs]
    best, found = math.inf, (h + 1, 0, 0)
    for spare in (0, 1, 2, 3, 4, 6, 8, 10, 12, 16):
        for share in (0.0, 0.25, 0.5, 0.75, 1.0):
            need = h + 1 + spare * (2 if share else 1)
            one_out = math.ceil(need * share / 2)
            plain = max(need - 2 * one_out, 0)
            each = size / (plain + one_out)
            bare = math.exp(-each)
            rows = plain + one_out * (1 + each)
            chance = n_docs * more_than(spare, SCARCE_MEAN + plain * bare + one_out * bare * (1 + each)) ** 2
            if rows + LINK_COST * chance < best:
                best, found = rows + LINK_COST * chance, (plain, one_out, spare)
    _allocated[size, h, n_docs] = found
    return found


def signatures(
    sets: np.ndarray, bounds: np.ndarray, size: np.ndarray, low: np.ndarray, percent: int, n_docs: int, salt: int, taking: np.ndarray | None = None
) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(set, signature) rows and poor[shift, set], for each set's own band (shift 0) and the band below (1).

    `sets` holds the elements of the universe that salt names, `size` the whole sets' sizes. Without
    `taking`, signatures of empty subsets are left out; with it (which sets take part, by shift), a
    set with more than e scarce segments sends those as well.
    """
    count_of = len(size)
    band = np.searchsorted(low, size, side="right") - 1
    plain, one_out, spare = (np.zeros(len(low), np.int64) for _ in range(3))
    for b in np.unique(np.concatenate((band, band - 1))):
        if b >= 0:
            high = int(low[b + 1] - 1) if b + 1 < len(low) else int(low[b] * 100 // percent)
            plain[b], one_out[b], spare[b] = allocate(high, most_different(high, percent), n_docs)
    owner, found, poor = [], [], np.zeros((2, count_of), dtype=bool)
    mixed, place = tk.mix(sets.copy(), 3), tk.mix(sets.copy(), 1000 + salt) >> tk.U(32)
    of = np.repeat(np.arange(count_of), np.diff(bounds))
    for shift in (0, 1):
        b = band - shift
        use = (size > 0) & (b >= 0)
        if taking is not None:
            use &= taking[shift]
        m = np.where(use, (plain + one_out)[np.maximum(b, 0)], 0)
        base = np.concatenate(([0], np.cumsum(m)))
        mine = use[of]
        o, x = of[mine], mixed[mine]
        seg = ((place[mine] * m[o].astype(tk.U)) >> tk.U(32)).astype(np.int64)
        slot = base[o] + seg
        count = np.bincount(slot, minlength=base[-1])
        order = np.argsort(slot, kind="stable")
        sums = np.concatenate((np.zeros(1, tk.U), np.cumsum(x[order])))
        cuts = np.concatenate(([0], np.cumsum(count)))
        total = sums[cuts[1:]] - sums[cuts[:-1]]
        doc = np.repeat(np.arange(count_of), m)
        index = np.arange(base[-1]) - base[doc]
        dropped = one_out[np.maximum(b, 0)]  # segments with v = 1 come first
        tag = (((salt + 1) << 48) + b[doc] * (1 << 32) + index).astype(tk.U) * tk.U(0xA24BAED4963EE407)
        scarce = count <= (index < dropped[doc])
        poor[shift] = use & (np.bincount(doc[scarce], minlength=count_of) > spare[np.maximum(b, 0)])
        every = poor[shift] if taking is not None else np.zeros(count_of, dtype=bool)
        send = (count > 0) | every[doc]
        owner.append(doc[send])
        found.append(tk.mix(total + tag, 5)[send])
        some = np.flatnonzero(seg < dropped[o])
        some = some[(count[slot[some]] > 1) | every[o[some]]]
        owner.append(o[some])
        found.append(tk.mix(total[slot[some]] - x[some] + tag[slot[some]], 5))
    return np.concatenate(owner), np.concatenate(found), poor


def bucket_keys(sets: np.ndarray, bounds: np.ndarray, frequent: np.ndarray, percent: int, n_docs: int) -> tuple[np.ndarray, np.ndarray]:
    """(set, signature) of both partitions; frequent is sorted."""
    size = np.diff(bounds)
    low = size_bands(int(size.max(initial=1)), percent)
    rare = np.ones(len(sets), dtype=bool)
    if len(frequent):
        rare = frequent[np.minimum(np.searchsorted(frequent, sets), len(frequent) - 1)] != sets
    upto = np.concatenate(([0], np.cumsum(rare)))[bounds]
    owner, sigs, poor = signatures(sets[rare], upto, size, low, percent, n_docs, 0)
    if not poor.any():
        return owner, sigs
    rest = poor.any(axis=0)
    other, more, _ = signatures(
        sets[np.repeat(rest, size)], np.concatenate(([0], np.cumsum(size[rest]))), size[rest], low, percent, n_docs, 1, poor[:, rest]
    )
    return np.concatenate((owner, np.flatnonzero(rest)[other])), np.concatenate((sigs, more))


def shingle_runs(batch: pa.RecordBatch, width: int) -> Iterator[tuple[int, int, np.ndarray, np.ndarray]]:
    """(first row, end row, shingles, bounds) of runs of a batch's texts."""
    buf, bounds = tk.raw(batch.column("text"))
    for a, b in tk.runs(bounds):
        at = bounds[a : b + 1] - bounds[a]
        yield a, b, *tk.shingles(tk.words(buf[bounds[a] : bounds[b]], at, tk.NOT_WHITE), width)


def set_hashes(sets: np.ndarray, cuts: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    out = []
    for salt in (1, 2):
        sums = np.concatenate((np.zeros(1, tk.U), np.cumsum(tk.mix(sets.copy(), salt))))
        out.append(sums[cuts[1:]] - sums[cuts[:-1]])
    return out[0], out[1]


def parity_fields(sets: np.ndarray, cuts: np.ndarray) -> pa.Array:
    """For each set, the parity of its elements at each bit of a field of 2 ** k bits, at least ELEMENT_BITS a element."""
    n = np.diff(cuts)
    bits = np.maximum(FIELD_BITS, 1 << np.ceil(np.log2(np.maximum(ELEMENT_BITS * n, 1))).astype(np.int64))
    base = np.concatenate(([0], np.cumsum(bits)))
    of = np.repeat(np.arange(len(n)), n)
    at = base[of] + (tk.mix(sets.copy(), 4) & (bits[of] - 1).astype(tk.U)).astype(np.int64)
    held = np.packbits((np.bincount(at, minlength=base[-1]) & 1).astype(bool))
    return pa.Array.from_buffers(pa.binary(), len(n), [None, pa.py_buffer((base // 8).astype(np.int32)), pa.py_buffer(held)])


def set_reader(width: int):
    """mapInArrow: (id, th, text) to size, hash and parity field of each set."""

    def read(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for a, b, sets, cuts in shingle_runs(batch, width):
                s1, s2 = set_hashes(sets, cuts)
                rest = [batch.column(c).slice(a, b - a) for c in ("id", "th")]
                yield pa.RecordBatch.from_arrays(
                    [*rest, tk.longs(np.diff(cuts)), tk.longs(s1), tk.longs(s2), parity_fields(sets, cuts)], ["id", "th", "n_shingles", "s1", "s2", "field"]
                )

    return read


def element_reader(width: int):
    """mapInArrow: (text) to (s1, elements) of each set."""

    def read(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for _, _, sets, cuts in shingle_runs(batch, width):
                yield pa.RecordBatch.from_arrays([tk.longs(set_hashes(sets, cuts)[0]), tk.lists(sets, cuts)], ["s1", "elements"])

    return read


def frequent_elements(texts: DataFrame, width: int, n_docs: int) -> np.ndarray:
    """Elements that FREQUENT distinct sets of the sample hold, the most frequent ones, sorted."""
    sample = texts.select("text").sample(min(1.0, SAMPLE / max(n_docs, 1)), seed=5)
    once = sample.mapInArrow(element_reader(width), "s1 long, elements array<long>").dropDuplicates(["s1"])
    held = once.select(F.explode("elements").alias("x")).groupBy("x").count().filter(F.col("count") >= FREQUENT)
    top = held.orderBy(F.desc("count"), "x").limit(FREQUENT_ELEMENTS).select("x").toArrow()
    return np.sort(top.column("x").to_numpy().astype(np.int64).view(tk.U))


def signature_packer(width: int, percent: int, n_docs: int, parts: int, frequent):
    """mapInArrow: (text) to packs (part, sigs, sets) of the signatures of sets this task has not met before.

    A set is named by its hash s1. A pack holds the signatures of many sets that go to one
    part, so that a signature costs its hash, its set's and little more.
    """

    def read(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        seen: set[int] = set()
        held: list[tuple[np.ndarray, np.ndarray]] = []
        size = 0

        def packs() -> pa.RecordBatch:
            sig, name = (np.concatenate(x) for x in zip(*held, strict=True))
            part = (sig % tk.U(parts)).astype(np.int32)
            order = np.argsort(part, kind="stable")
            found, at = np.unique(part[order], return_index=True)
            cuts = np.append(at, len(order))
            return pa.RecordBatch.from_arrays([pa.array(found), tk.lists(sig[order], cuts), tk.lists(name[order], cuts)], ["part", "sigs", "sets"])

        for batch in batches:
            for _, _, sets, cuts in shingle_runs(batch, width):
                n = np.diff(cuts)
                s1, _ = set_hashes(sets, cuts)
                fresh = np.zeros(len(n), dtype=bool)
                for i, key in enumerate(s1.tolist()):
                    if key not in seen:
                        seen.add(key)
                        fresh[i] = True
                if len(seen) > SEEN:
                    seen.clear()
                owner, sigs = bucket_keys(sets[np.repeat(fresh, n)], np.concatenate(([0], np.cumsum(n[fresh]))), frequent.value, percent, n_docs)
                held.append((sigs, s1[fresh][owner]))
                size += len(sigs)
                if size >= PACKED:
                    yield packs()
                    held, size = [], 0
        if size:
            yield packs()

    return read


def bucket_reader(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """mapInArrow over packs sorted by part: (bucket, s1) of the signatures that several sets have.

    A bucket is named by a hash of its members, so that equal buckets become one. A part that
    is too large for one go comes in chunks: there a bucket is named by its signature, and one
    set is kept for each signature of the part.
    """
    part, sigs, names, size, chunked = None, [], [], 0, False

    def buckets(whole: bool) -> pa.RecordBatch:
        sig, name = np.concatenate(sigs), np.concatenate(names)
        order = np.lexsort((name, sig))
        sig, name = sig[order], name[order]
        once = np.concatenate(([True], (sig[1:] != sig[:-1]) | (name[1:] != name[:-1])))
        sig, name = sig[once], name[once]
        heads = np.flatnonzero(np.concatenate(([True], sig[1:] != sig[:-1])))
        count = np.diff(np.append(heads, len(sig)))
        sigs[:], names[:] = [sig[heads]], [name[heads]]
        many = count > 1
        if not many.any():
            return pa.RecordBatch.from_arrays([pa.array([], pa.int64())] * 2, ["bucket", "s1"])
        label = tk.mix(np.add.reduceat(tk.mix(name.copy(), 8), heads) + count.astype(tk.U)) if whole else sig[heads]
        pick = np.flatnonzero(many)
        pick = pick[np.unique(label[pick], return_index=True)[1]]
        of = np.repeat(np.arange(len(pick)), count[pick])
        at = np.arange(len(of)) - np.repeat(np.cumsum(count[pick]) - count[pick], count[pick]) + heads[pick][of]
        return pa.RecordBatch.from_arrays([tk.longs(label[pick][of]), tk.longs(name[at])], ["bucket", "s1"])

    for batch in batches:
        where = batch.column("part").to_numpy(zero_copy_only=False)
        bounds = [batch.column(c).offsets.to_numpy() for c in ("sigs", "sets")]
        flat = [batch.column(c).values.to_numpy(zero_copy_only=False).view(tk.U) for c in ("sigs", "sets")]
        for i in range(batch.num_rows):
            if where[i] != part and size:
                yield buckets(not chunked)
                sigs, names, size, chunked = [], [], 0, False
            part = where[i]
            sigs.append(flat[0][bounds[0][i] : bounds[0][i + 1]].copy())
            names.append(flat[1][bounds[1][i] : bounds[1][i + 1]].copy())
            size += len(sigs[-1])
            if size >= 2 * PACKED:
                chunked = True
                yield buckets(False)
                size = len(sigs[0])
    if size:
        yield buckets(not chunked)


def passing(size: np.ndarray, fields: list[bytes], sides: np.ndarray, percent: int) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """(i, j) of the pairs i < j that may be similar, by sizes and parity fields; if sides differ, only pairs across.

    Rows of i come in order. Fields of more bits are folded to the shortest one's.
    """
    k, words = len(size), min(map(len, fields)) // 8
    held = np.empty((k, words), dtype=np.uint64)
    for i, f in enumerate(fields):
        x = np.frombuffer(f, np.uint64)
        while len(x) > words:
            x = x[: len(x) // 2] ^ x[len(x) // 2 :]
        held[i] = x
    across, step = sides.any() and not sides.all(), max(1, COMPARED_WORDS // (k * words))
    for a in range(0, k, step):
        b = min(k, a + step)
        differ = np.bitwise_count(held[a:b, None, :] ^ held[None, a:, :]).sum(axis=2, dtype=np.int64)
        may = differ <= (100 - percent) * (size[a:b, None] + size[None, a:]) // (100 + percent)
        may &= np.arange(a, b)[:, None] < np.arange(a, k)[None, :]
        if across:
            may &= sides[a:b, None] != sides[None, a:]
        i, j = np.nonzero(may)
        yield i + a, j + a


def pair_finder(percent: int, first: bool):
    """mapInArrow over rows sorted by (bucket, lft, rgt, node): pairs (a, b) to check exactly.

    The first round takes for each set the least one that passes, the second all passing
    pairs of different classes.
    """

    def find(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        key, rows = None, []

        def flush() -> tuple[np.ndarray, np.ndarray]:
            node, size, side, label = (np.array(x, dtype=np.int64) for x in list(zip(*rows, strict=True))[:4])
            lo, hi = [np.zeros(0, np.int64)], [np.zeros(0, np.int64)]
            met = np.zeros(len(node), dtype=bool)
            if len(rows) > 1 and (key[1] == key[2] or side.any() != side.all()):
                for i, j in passing(size, [r[4] for r in rows], side if key[1] != key[2] else np.zeros(len(node), np.int64), percent):
                    if first:
                        take = np.unique(j, return_index=True)[1]  # rows come in order of i
                        take = take[~met[j[take]]]
                        met[j[take]] = True
                    else:
                        take = np.flatnonzero(label[i] != label[j])
                    lo.append(node[i[take]])
                    hi.append(node[j[take]])
            a, b = np.concatenate(lo), np.concatenate(hi)
            return np.minimum(a, b), np.maximum(a, b)

        out, held = [], 0

        def pairs() -> pa.RecordBatch:
            """What was found, each pair once; in the first round for each set the least one that it met in any bucket."""
            a, b = (np.concatenate(x) for x in zip(*out, strict=True))
            order = np.lexsort((a, b))
            a, b = a[order], b[order]
            new = np.concatenate(([True], b[1:] != b[:-1]))[: len(b)]
            if not first:
                new[1:] |= a[1:] != a[:-1]
            return pa.RecordBatch.from_arrays([pa.array(a[new]), pa.array(b[new])], ["a", "b"])

        for batch in batches:
            columns = [batch.column(c).to_pylist() for c in ("bucket", "lft", "rgt", "node", "n", "side", "label", "field")]
            for bucket, lft, rgt, *rest in zip(*columns, strict=True):
                if key != (bucket, lft, rgt):
                    if len(rows) > 1:
                        out.append(flush())
                        held += len(out[-1][0])
                    key, rows = (bucket, lft, rgt), []
                rows.append(rest)
            if held > FOUND_PAIRS:
                yield pairs()
                out, held = [], 0
        if len(rows) > 1:
            out.append(flush())
        if out:
            yield pairs()

    return find


def candidate_pairs(members: DataFrame, percent: int, first: bool) -> DataFrame:
    """(a, b) among members(bucket, node, n, field, label), distinct."""
    n = partitions(members)
    large = cut(members.groupBy("bucket").agg(F.ceil(F.count("*") / BLOCK).cast("int").alias("slots")).filter("slots > 1"), "join-large")
    one = [F.lit(0).alias("lft"), F.lit(0).alias("rgt"), F.lit(0).alias("side")]
    columns = ["bucket", "node", "n", "label", "field"]
    if large.isEmpty():
        dealt = members.select(*columns, *one)
    else:
        slot = F.pmod(F.xxhash64("node"), F.col("slots")).cast("int")
        pairs = F.transform(
            F.sequence(F.lit(0), F.col("slots") - 1),
            lambda j: F.struct(F.least(j, "slot").alias("lft"), F.greatest(j, "slot").alias("rgt"), (j < F.col("slot")).cast("int").alias("side")),
        )
        split = members.join(large, "bucket").withColumn("slot", slot).select(*columns, F.inline(pairs))
        dealt = members.join(large, "bucket", "left_anti").select(*columns, *one).unionByName(split)
    dealt = dealt.repartition(n, "bucket", "lft", "rgt").sortWithinPartitions("bucket", "lft", "rgt", "node")
    return dealt.mapInArrow(pair_finder(percent, first), "a long, b long").distinct()


def shingle_reader(width: int):
    """mapInArrow: (node, s1, s2, roles, text) to (node, roles, shingles) of the texts whose set has these hashes."""

    def read(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for a, b, sets, cuts in shingle_runs(batch, width):
                part = batch.slice(a, b - a)
                s1, s2 = set_hashes(sets, cuts)
                right = s1.view(np.int64) == part.column("s1").to_numpy(zero_copy_only=False)
                right &= s2.view(np.int64) == part.column("s2").to_numpy(zero_copy_only=False)
                yield pa.RecordBatch.from_arrays([part.column("node"), part.column("roles"), tk.lists(sets, cuts)], ["node", "roles", "shingles"]).filter(pa.array(right))

    return read


def pair_checker(percent: int):
    """mapInArrow over rows sorted by (hub, salt, side, node): links of a hub (side 0) with the sets after it."""

    def check(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        hub, own, last = None, np.zeros(0, tk.U), None
        for batch in batches:
            flat, bounds = batch.column("shingles").values, batch.column("shingles").offsets.to_numpy()
            values = flat.to_numpy(zero_copy_only=False).view(tk.U)
            names, nodes = (batch.column(c).to_numpy(zero_copy_only=False) for c in ("hub", "node"))
            links: list[tuple[int, int]] = []
            for i, (h, node) in enumerate(zip(names.tolist(), nodes.tolist(), strict=True)):
                mine = values[bounds[i] : bounds[i + 1]]
                if node == h:
                    hub, own, last = h, mine.copy(), None
                elif node != last:
                    last = node
                    shared = len(np.intersect1d(own, mine, assume_unique=True)) if h == hub else 0
                    if 100 * shared >= percent * (len(own) + len(mine) - shared) > 0:
                        links.append((h, node))
            columns = list(zip(*links, strict=True)) or [(), ()]
            yield pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in columns], ["a", "b"])

    return check


def hinted(rows: DataFrame) -> DataFrame:
    return F.broadcast(rows) if rows.count() <= BROADCAST_IDS else rows


def verified(texts: DataFrame, distinct: DataFrame, pairs: DataFrame, width: int, percent: int) -> DataFrame:
    """The pairs (a, b) of nodes whose sets are similar; a set is sent once for each hub that it is held against."""
    fan = pairs.groupBy("a").agg(F.ceil(F.count("*") / CHECKS).cast("int").alias("salts"))
    salted = pairs.join(fan, "a").withColumn("salt", F.pmod(F.xxhash64("b"), F.col("salts")).cast("int"))
    salted = cut(salted.select("a", "b", "salt"), "join-salted")
    role = lambda side: F.struct(F.col("a").alias("hub"), "salt", F.lit(side).alias("side")).alias("role")
    roles = salted.select(F.col("b").alias("node"), role(1)).union(salted.select("a", "salt").distinct().select(F.col("a").alias("node"), role(0)))
    asked = cut(
        roles.groupBy("node").agg(F.collect_list("role").alias("roles")).join(distinct.select("node", "rep", "s1", "s2"), "node"), "join-asked"
    )
    found = texts.join(hinted(asked), texts["id"] == asked["rep"]).select("node", "s1", "s2", "roles", "text")
    sets = found.mapInArrow(shingle_reader(width), "node long, roles array<struct<hub:bigint,salt:int,side:int>>, shingles array<long>")
    dealt = sets.select("node", F.inline("roles"), "shingles").repartition(partitions(texts), "hub", "salt").sortWithinPartitions("hub", "salt", "side", "node")
    return dealt.mapInArrow(pair_checker(percent), "a long, b long")


def set_classes(docs: DataFrame, width: int = 3, percent: int = 90) -> DataFrame:
    """(id, th, n_shingles, class, least): for each row its doc_id, its text's xxhash64, its set's class and the least id of that.

    Rows of a class reach each other by links. A row without id or words has no class; its least id is its own.
    """
    ship("nodeflux.llm.textkit", "nodeflux.llm.jaccard")
    context = docs.sparkSession.sparkContext
    texts = docs.select(F.col("doc_id").alias("id"), F.xxhash64("text").alias("th"), "text")
    kind = docs.schema["doc_id"].dataType.simpleString()
    schema = f"id {kind}, th long, n_shingles long, s1 long, s2 long, field binary"
    slim = cut(texts.mapInArrow(set_reader(width), schema), "join-sets")
    n_docs = slim.count()
    named = slim.filter("n_shingles > 0 and id is not null")
    distinct = cut(
        named.groupBy("s1", "s2").agg(F.min("id").alias("rep"), F.count("*").alias("copies"), F.first("n_shingles").alias("n"), F.first("field").alias("field"))
        .withColumn("node", F.monotonically_increasing_id()), "join-distinct",
    )
    named_texts = texts.filter("id is not null")
    frequent = context.broadcast(frequent_elements(named_texts, width, n_docs))
    n = partitions(docs)
    packs = named_texts.select("text").mapInArrow(
        signature_packer(width, percent, n_docs, PARTS * n, frequent), "part int, sigs array<long>, sets array<long>"
    )
    buckets = packs.repartition(n, "part").sortWithinPartitions("part").mapInArrow(bucket_reader, "bucket long, s1 long").distinct()
    members = cut(buckets.join(distinct.select("s1", "node", "n", "field"), "s1").drop("s1"), "join-members")
    frequent.destroy()

    tried = cut(candidate_pairs(members.withColumn("label", F.lit(0).cast("long")), percent, True), "join-pairs")
    links = cut(verified(named_texts, distinct, tried, width, percent), "join-links")
    classes = components(links)
    labelled = members.join(classes.select(F.col("id").alias("node"), "comp"), "node", "left").withColumn("label", F.coalesce("comp", "node")).drop("comp")
    torn = labelled.groupBy("bucket").agg(F.min("label").alias("least"), F.max("label").alias("most")).filter("least <> most").select("bucket")
    rest = cut(labelled.join(torn, "bucket", "left_semi"), "join-torn")
    more = cut(candidate_pairs(rest, percent, False).join(tried, ["a", "b"], "left_anti"), "join-more")
    if not more.isEmpty():
        discard(classes)
        classes = components(links.union(verified(named_texts, distinct, more, width, percent)))
    for table in (members, rest, tried, more, links):
        discard(table)
    named_classes = distinct.select("s1", "s2", "rep", "node").join(classes.select(F.col("id").alias("node"), "comp"), "node", "left")
    named_classes = named_classes.select("s1", "s2", "rep", F.coalesce("comp", "node").alias("class"))
    least = named_classes.groupBy("class").agg(F.min("rep").alias("least"))
    whole = cut(named_classes.drop("rep").join(least, "class"), "join-classes")
    rows = slim.select("id", "th", "n_shingles", F.when(F.col("n_shingles") > 0, F.col("s1")).alias("s1"), "s2").join(whole, ["s1", "s2"], "left")
    alone = F.col("id").isNull()  # a set may be that of a row with an id, too
    return rows.select("id", "th", "n_shingles", F.when(~alone, F.col("class")).alias("class"), F.when(~alone, F.coalesce("least", "id")).alias("least"))


def jaccard_components(docs: DataFrame, width: int = 3, percent: int = 90) -> DataFrame:
    """(doc_id, n_shingles, component_id): documents of whose shingles `percent` in 100 are shared are linked."""
    rows = cut(set_classes(docs, width, percent), "join-rows")
    repeated = rows.filter("id is not null").groupBy("id").agg(F.min("class").alias("a"), F.max("class").alias("b"), F.count("class").alias("named"), F.count("*").alias("rows"))
    torn = cut(repeated.filter("rows > 1 and (a <> b or named < rows)").select("id", "a"), "join-torn-ids")
    if not torn.isEmpty():  # rows of one id are one node and join their classes
        joined = components(rows.join(torn, "id").filter("class is not null").select("a", F.col("class").alias("b")))
        rows = rows.join(joined.select(F.col("id").alias("class"), "comp"), "class", "left").withColumn("class", F.coalesce("comp", "class")).drop("comp")
        of_class = rows.filter("class is not null").groupBy("class").agg(F.min("least").alias("first"))
        rows = rows.join(of_class, "class", "left").withColumn("least", F.coalesce("first", "least")).drop("first")
        of_id = rows.join(torn.select("id"), "id").groupBy("id").agg(F.min("least").alias("first"))
        rows = rows.join(of_id, "id", "left").withColumn("least", F.coalesce("first", "least"))
    return rows.select(F.col("id").alias("doc_id"), "n_shingles", F.col("least").alias("component_id"))


def keep_first(docs: DataFrame, width: int = 5, percent: int = 80) -> DataFrame:
    """docs with one row of each class: the least doc_id's, of its texts the one with the least hash.

    Rows without id or words are no copies of anything and stay; of rows that repeat id and
    text one stays; rows of one id with texts of different classes stay all. Columns keep
    their names and types, whatever they are called.
    """
    rows = cut(set_classes(docs, width, percent), "near-rows")
    heads = rows.filter("class is not null and id = least").groupBy("class").agg(F.min("id").alias("id"), F.min("th").alias("th"))
    text_hash, head, head_hash = fresh_names(docs, "text_hash", "head", "head_hash")
    heads = cut(heads.select(F.col("id").alias(head), F.col("th").alias(head_hash)), "near-kept")
    alone = F.col("doc_id").isNull() | (F.btrim(F.coalesce("text", F.lit("")), F.lit(WHITE)) == "")
    marked = docs.filter(~alone).withColumn(text_hash, F.xxhash64("text"))
    kept = marked.join(heads, (F.col("doc_id") == F.col(head)) & (F.col(text_hash) == F.col(head_hash)), "left_semi").dropDuplicates(["doc_id", text_hash])
    return kept.select(*docs.columns).unionByName(docs.filter(alone))


def op8_jaccard_join(spark, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text")
    return jaccard_components(docs, 3, 90)
