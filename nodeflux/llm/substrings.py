"""Exact removal of repeated byte strings: merged Burrows-Wheeler transforms of shards.

Sorting every suffix of the corpus is not needed, as most of it can be ruled out exactly. A
string of `span` bytes owns an anchor: the leftmost least of its K-gram hashes. Equal strings
own equal anchors, so consecutive starts with one anchor form a stretch, and a stretch whose
anchor's hash is unique in the corpus holds no repeated string. What is left is decided by
suffix order, in two streams:

1. Stretches of one kind (equal hashes of anchor and whole bytes) that stand at several places.
   Their first and last places are taken; consecutive kinds with the same two documents make
   one run of bytes of either. The runs of first places and of last places get the transforms
   of their own shards, which are merged. A kind whose starts all have a common prefix of
   `span` bytes with a neighbour in the merged order is repeated, at every place that it has.
2. Kinds that stand once under an anchor that has several, mostly the ends of copied passages.
   One place of each kind of such an anchor is taken, narrowed to the starts whose middle bytes
   stand in another stretch, and dealt over the shards that are merged. An anchor with very many
   kinds is dealt by those middle bytes instead, ever closer to whole strings; whole strings
   that still are very many are kinds as in 1.

A shard's suffixes are sorted by themselves. Shards are merged by interleave refinement: a
transform's symbols are the STEP bytes in front of each suffix, and each round stably
redistributes the interleave by these symbols, which orders the merged suffixes by STEP bytes
more. The round in which neighbours part gives their common prefix, without sorting again.
Neighbours with a common prefix of `span` bytes are the repeats; nothing else marks any.
Symbols are ordered by their 64-bit hashes and not by their bytes: the order is another than
the alphabet's, but equal prefixes stand together in it as well, and only that is used.

Defined results: a null or empty text has no bytes and loses none; every row is judged for
itself, so rows that repeat a doc_id stay apart by the text's hash (equal rows lose the same
bytes); ids may be null; an empty table gives none; other columns of the input play no part.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import textkit as tk
from .common import cut, discard, partitions, row_id, ship

K = 96
#: Stretches of one group that are resolved together; a larger group is dealt by closer keys, of starts of these numbers.
GROUP_STRETCHES, WIDTHS = 2000, (26, 6, 1)
#: Bytes of a symbol of the transforms; `span` is a multiple.
STEP = 100
#: Starts that are narrowed down together.
NARROW = 26
#: Bytes of a shard whose suffixes are sorted at once, and of stretches that are gathered for a merge.
SHARD_BYTES, MERGED_BYTES = 1 << 19, 1 << 20


def stretches(buf: np.ndarray, bounds: np.ndarray, span: int) -> tuple[np.ndarray, ...]:
    """(text, first start, starts, anchor's offset, anchor's hash, stretch's hash) of each stretch, in order."""
    n = len(buf)
    none = np.zeros(0, np.int64)
    if n < span:
        return none, none, none, none, np.zeros(0, tk.U), np.zeros(0, tk.U)
    width = span - K + 1
    sums = np.zeros(n + 1, dtype=tk.U)
    np.cumsum(tk.BYTE_HASH[buf] * tk.powers(tk.BASE, n), out=sums[1:])
    back = tk.powers(tk.BASE_INVERSE, n)
    grams = tk.mix((sums[K:] - sums[:-K]) * back[: n - K + 1], 9)
    # hash above, position below: the least key is the leftmost least hash
    least = (grams & tk.U(0xFFFFFFFF00000000)) | np.arange(len(grams), dtype=tk.U)
    have = 1
    while 2 * have <= width:
        least = np.minimum(least[:-have], least[have:])
        have *= 2
    if have < width:
        least = np.minimum(least[: len(least) - (width - have)], least[width - have :])
    owner = (least & tk.U(0xFFFFFFFF)).astype(np.int64)
    # starts whose string ends within the text
    text = np.repeat(np.arange(len(bounds) - 1), np.maximum(np.diff(bounds) - span + 1, 0))
    if not len(text):
        return none, none, none, none, np.zeros(0, tk.U), np.zeros(0, tk.U)
    long = np.diff(bounds) >= span
    many = (np.diff(bounds) - span + 1)[long]
    start = np.arange(len(text)) - np.repeat(np.cumsum(many) - many, many) + bounds[text]
    own = owner[start]
    head = np.flatnonzero(np.concatenate(([True], (own[1:] != own[:-1]) | (text[1:] != text[:-1]))))
    count = np.diff(np.append(head, len(own)))
    first = start[head]
    upto = first + count - 1 + span
    whole = tk.mix((sums[upto] - sums[first]) * back[first] + count.astype(tk.U) * tk.U(tk.BASE), 13)
    t = text[head]
    return t, first - bounds[t], count, own[head] - first, grams[own[head]], whole


ANCHORS = "id long, th long, n_bytes long, anchor array<long>, whole array<long>, first array<int>, count array<int>"


def anchor_reader(span: int):
    """mapInArrow: (id, th, text) to the stretches of each text, as arrays."""

    def read(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            buf, bounds = tk.raw(batch.column("text"))
            for a, b in tk.runs(bounds):
                at = bounds[a : b + 1] - bounds[a]
                text, first, count, _, anchor, whole = stretches(buf[bounds[a] : bounds[b]], at, span)
                cuts = np.searchsorted(text, np.arange(b - a + 1))
                ints = lambda x: pa.ListArray.from_arrays(pa.array(cuts.astype(np.int32)), pa.array(x.astype(np.int32)))  # noqa: B023, E731
                yield pa.RecordBatch.from_arrays(
                    [batch.column("id").slice(a, b - a), batch.column("th").slice(a, b - a), tk.longs(np.diff(at)),
                     tk.lists(anchor, cuts), tk.lists(whole, cuts), ints(first), ints(count)],
                    ["id", "th", "n_bytes", "anchor", "whole", "first", "count"],
                )

    return read


# -- suffixes of shards and their merge ---------------------------------------------------


def window_hashes(data: np.ndarray, width: int) -> np.ndarray:
    """Hash of the `width` symbols from each place of a cyclic text."""
    n = len(data)
    reps = -(-width // n)
    twice = np.concatenate((data, *[data] * reps))[: n + width]
    sums = np.zeros(n + width + 1, dtype=tk.U)
    np.cumsum(SYMBOL_HASH[twice] * tk.powers(tk.BASE, n + width), out=sums[1:])
    return tk.mix((sums[width : width + n] - sums[:n]) * tk.powers(tk.BASE_INVERSE, n), 21)


def ranks(keys: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(order, rank): places by key, and the dense rank of each place's key."""
    order = np.argsort(keys)
    ordered = keys[order]
    rank = np.empty(len(keys), dtype=np.int64)
    rank[order] = np.cumsum(np.concatenate(([0], (ordered[1:] != ordered[:-1]).astype(np.int64))))
    return order, rank


SYMBOL_HASH = tk.mix(np.arange(257, dtype=tk.U), 23)


class Shard:
    """Stretches laid end to end, each closed by a zero and all by STEP zeros, with their suffixes in order.

    Bytes are kept plus one. `values` are the shard's symbols in order (of their hashes), rank[i] is the
    place among them of the symbol that begins at i. The transform that is merged is the rank of
    the symbol in front of each suffix, in suffix order.
    """

    def __init__(self, data: np.ndarray, order: np.ndarray, rank: np.ndarray, values: np.ndarray) -> None:
        self.data, self.order, self.rank, self.values = data, order, rank, values

    @staticmethod
    def of(parts: list[np.ndarray], span: int) -> Shard:
        one, end = np.zeros(1, np.uint16), np.zeros(STEP, np.uint16)
        data = np.concatenate([x for part in parts for x in (part.astype(np.uint16) + 1, one)] + [end])
        symbol = window_hashes(data, STEP)
        order, first = ranks(symbol)
        values = np.empty(first[order[-1]] + 1, dtype=tk.U)
        values[first] = symbol
        rank, have, top = first, STEP, len(data) + 1
        while have < span:  # order by twice as much, at last by what is left
            more = min(have, span - have)
            order, rank = ranks(rank * top + np.roll(rank if more == have else first, -have if more == have else -(span - STEP)))
            have += more if more == have else STEP
        return Shard(data, order, first, values)

    def by_symbol(self, names: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(places of the transform sorted stably by symbol, symbols in that order); names: of the ranks."""
        before, n = self.rank[self.order - STEP], len(self.order)
        places = np.argsort(before * n + np.arange(n))
        return places, names[before[places]]


def merge(a: Shard, b: Shard, span: int) -> tuple[Shard, np.ndarray]:
    """The merged shard and, for neighbours in its order, their common prefix in whole symbols, up to span.

    The interleave says for each place whether a suffix of a or of b stands there. Dealing the
    places stably by the symbols before their suffixes gives the order by one symbol more, as
    both shards' own orders stay as they are: two runs that are sorted already are merged.
    """
    na, nb = len(a.order), len(b.order)
    n = na + nb
    values = np.sort(np.concatenate((a.values, b.values)))
    values = values[np.concatenate(([True], values[1:] != values[:-1]))]
    names = [np.searchsorted(values, x.values) for x in (a, b)]
    (places_a, symbols_a), (places_b, symbols_b) = a.by_symbol(names[0]), b.by_symbol(names[1])
    symbols = np.concatenate((symbols_a, symbols_b))
    at_a, at_b = np.arange(na), np.arange(na, n)
    group = np.zeros(n, dtype=np.int64)  # places of one group share the prefix so far
    prefix = np.full(n, span, dtype=np.int32)
    for done in range(0, span, STEP):
        at = np.concatenate((at_a[places_a], at_b[places_b]))
        order = np.argsort(symbols * n + at, kind="stable")
        s, g = symbols[order], group[at[order]]
        new = np.concatenate(([True], (s[1:] != s[:-1]) | (g[1:] != g[:-1])))
        prefix[new & (prefix == span)] = done
        group = np.cumsum(new) - 1
        side = order >= na
        at_a, at_b = np.flatnonzero(~side), np.flatnonzero(side)
    order = np.empty(n, dtype=np.int64)
    order[at_a], order[at_b] = a.order, b.order + len(a.data)
    return Shard(np.concatenate((a.data, b.data)), order, np.concatenate((names[0][a.rank], names[1][b.rank])), values), prefix


def repeated_starts(parts: list[np.ndarray], counts: list[int], span: int, shard_bytes: int = SHARD_BYTES, sides: list[int] | None = None) -> list[np.ndarray]:
    """For each part, which of its first counts[i] starts have a span-byte string that stands elsewhere too.

    Parts are dealt over two shards or more; with sides, those of either side to shards of their own.
    """
    if not parts:
        return []
    count = max(2, sum(map(len, parts)) // shard_bytes)
    count += count % 2
    dealt: list[list[int]] = [[] for _ in range(count)]
    for i in range(len(parts)):
        dealt[i % count if sides is None else 2 * (i % (count // 2)) + sides[i]].append(i)
    where, shards, base = np.zeros(len(parts), dtype=np.int64), [], 0
    for held in filter(None, dealt):
        shards.append(Shard.of([parts[i] for i in held], span))
        size = np.array([len(parts[i]) + 1 for i in held])
        where[held] = base + np.cumsum(size) - size
        base += len(shards[-1].data)
    prefix = None
    while len(shards) > 1:
        paired = [merge(shards[i], shards[i + 1], span) if i + 1 < len(shards) else (shards[i], None) for i in range(0, len(shards), 2)]
        shards, prefix = [s for s, _ in paired], paired[0][1]
    if prefix is None:  # one part alone
        return [np.zeros(c, dtype=bool) for c in counts]
    same, whole = prefix >= span, shards[0]
    hit = np.zeros(len(whole.data), dtype=bool)
    hit[whole.order[1:][same[1:]]] = True
    hit[whole.order[:-1][same[1:]]] = True
    return [hit[w : w + c] for w, c in zip(where.tolist(), counts, strict=True)]


def narrowed(data: list[np.ndarray], counts: np.ndarray, at: np.ndarray, span: int) -> list[tuple[int, int, int]]:
    """(row, first start, starts) that may be repeated.

    Starts whose distance to the anchor falls in one range of NARROW share span - NARROW + 1
    bytes around the anchor; if these stand in no other stretch, no such start is repeated.
    """
    flat = np.concatenate(data)
    begin = np.concatenate(([0], np.cumsum([len(d) for d in data])))[:-1]
    sums = np.zeros(len(flat) + 1, dtype=tk.U)
    np.cumsum(tk.BYTE_HASH[flat] * tk.powers(tk.BASE, len(flat)), out=sums[1:])
    back = tk.powers(tk.BASE_INVERSE, len(flat) + 1)
    rows, lows, highs, keys = [], [], [], []
    for q in range((span - K) // NARROW + 1):
        low, high = np.maximum(0, at - NARROW * q - NARROW + 1), np.minimum(counts - 1, at - NARROW * q)
        use = np.flatnonzero(low <= high)
        s = begin[use] + at[use] - NARROW * q
        rows.append(use)
        lows.append(low[use])
        highs.append(high[use])
        keys.append(tk.mix((sums[s + span - NARROW + 1] - sums[s]) * back[s], q))
    row, low, high, key = (np.concatenate(x) for x in (rows, lows, highs, keys))
    _, inverse, held = np.unique(key, return_inverse=True, return_counts=True)
    alive = held[inverse] > 1
    out: list[tuple[int, int, int]] = []
    for r, a, b in sorted(zip(row[alive].tolist(), low[alive].tolist(), high[alive].tolist(), strict=True)):
        if out and out[-1][0] == r and out[-1][1] + out[-1][2] == a:
            out[-1] = (r, out[-1][1], b + 1 - out[-1][1])
        else:
            out.append((r, a, b + 1 - a))
    return out


SPANS = "id long, th long, s int, e int"
KIND = "struct<first:int,count:int,anchor:bigint,whole:bigint>"
PIECES = f"grp long, role int, id long, th long, first int, count int, place int, data binary, kinds array<{KIND}>"
FIRST, LAST, OPEN = 0, 1, 2


def anchor_place(data: np.ndarray, anchor: np.uint64) -> int:
    """Where the anchor's K-gram begins in a stretch: the owner of its first start is the leftmost."""
    sums = np.zeros(len(data) + 1, dtype=tk.U)
    np.cumsum(tk.BYTE_HASH[data] * tk.powers(tk.BASE, len(data)), out=sums[1:])
    grams = tk.mix((sums[K:] - sums[:-K]) * tk.powers(tk.BASE_INVERSE, len(data))[: len(data) - K + 1], 9)
    return int((grams == anchor).argmax())


def piece_batch(rows: list[tuple]) -> pa.RecordBatch:
    """PIECES rows: (grp, role, id, th, first, count, place, data, kinds)."""
    kinds = pa.list_(pa.struct([("first", pa.int32()), ("count", pa.int32()), ("anchor", pa.int64()), ("whole", pa.int64())]))
    types = (pa.int64(), pa.int32(), pa.int64(), pa.int64(), pa.int32(), pa.int32(), pa.int32(), pa.binary(), kinds)
    names = [x.split()[0] for x in PIECES.split(", ")[:8]] + ["kinds"]
    columns = list(zip(*rows, strict=True)) or [()] * len(types)
    return pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(columns, types, strict=True)], names)


def piece_reader(span: int):
    """mapInArrow: (id, th, text, picks) to pieces: open stretches one by one, others as runs of consecutive stretches."""

    def read(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            buf, bounds = tk.raw(batch.column("text"))
            ids, hashes = batch.column("id").to_pylist(), batch.column("th").to_pylist()
            out: list[tuple] = []
            for i, picks in enumerate(batch.column("picks").to_pylist()):
                text, runs = buf[bounds[i] : bounds[i + 1]], []
                for x in sorted(picks, key=lambda x: (x["role"], x["grp"], x["first"])):
                    kind = {k: x[k] for k in ("first", "count", "anchor", "whole")}
                    if x["role"] != OPEN and runs and runs[-1][:2] == [x["grp"], x["role"]] and runs[-1][2] + runs[-1][3] == x["first"]:
                        runs[-1][3] += x["count"]
                        runs[-1][4].append(kind)
                    else:
                        runs.append([x["grp"], x["role"], x["first"], x["count"], [kind]])
                for grp, role, first, count, kinds in runs:
                    data = text[first : first + count + span - 1]
                    place = anchor_place(data, np.uint64(kinds[0]["anchor"] % (1 << 64))) if role == OPEN else 0
                    out.append((grp, role, ids[i], hashes[i], first, count, place, data.tobytes(), kinds if role == FIRST else None))
                if len(out) >= 2000:
                    yield piece_batch(out)
                    out = []
            yield piece_batch(out)

    return read


def gathered(batches: Iterator[pa.RecordBatch], columns: tuple[str, ...]) -> Iterator[list[tuple]]:
    """Rows sorted by grp, whole groups together, in lists of about MERGED_BYTES of data; grp is the first column, data the second."""
    rows: list[tuple] = []
    size, last = 0, None
    for batch in batches:
        for row in zip(*(batch.column(c).to_pylist() for c in columns), strict=True):
            if row[0] != last and size >= MERGED_BYTES:
                yield rows
                rows, size = [], 0
            rows.append(row)
            size += len(row[1])
            last = row[0]
    if rows:
        yield rows


def confirmer(span: int):
    """mapInArrow over pieces of first and last places, sorted by grp: the kinds (anchor, whole) whose starts all are repeated."""

    def confirm(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for rows in gathered(batches, ("grp", "data", "role", "first", "count", "kinds")):
            hits = repeated_starts([np.frombuffer(r[1], np.uint8) for r in rows], [r[4] for r in rows], span, sides=[r[2] for r in rows])
            found = [
                (k["anchor"], k["whole"])
                for (_, _, role, first, _, kinds), hit in zip(rows, hits, strict=True) if role == FIRST
                for k in kinds if hit[k["first"] - first : k["first"] - first + k["count"]].all()
            ]
            columns = list(zip(*found, strict=True)) or [(), ()]
            yield pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in columns], ["anchor", "whole"])

    return confirm


def resolver(span: int):
    """mapInArrow over open pieces sorted by grp: spans of starts that occur elsewhere."""

    def resolve(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for rows in gathered(batches, ("grp", "data", "id", "th", "first", "count", "place")):
            data = [np.frombuffer(r[1], np.uint8) for r in rows]
            alive = narrowed(data, np.array([r[5] for r in rows]), np.array([r[6] for r in rows]), span)
            found = repeated_starts([data[i][a : a + n + span - 1] for i, a, n in alive], [n for _, _, n in alive], span)
            out: list[tuple[int, int, int, int]] = []
            for (i, a, _), hit in zip(alive, found, strict=True):
                doc, th, first = rows[i][2:5]
                edge = np.flatnonzero(np.diff(np.concatenate(([0], hit.view(np.int8), [0]))))
                for s, e in zip(edge[::2].tolist(), edge[1::2].tolist(), strict=True):
                    out.append((doc, th, first + a + s, first + a + e - 1 + span))
            cols = list(zip(*out, strict=True)) or [[]] * 4
            kinds = (pa.int64(), pa.int64(), pa.int32(), pa.int32())
            yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(cols, kinds, strict=True)], ["id", "th", "s", "e"])

    return resolve


def closer(span: int, width: int):
    """mapInArrow: open pieces to pieces of at most `width` starts, grouped by the bytes that all of a piece's strings share."""

    def deal(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            out = []
            for grp, role, doc, th, first, count, at, data, _ in zip(*(batch.column(c).to_pylist() for c in batch.schema.names), strict=True):
                x = np.frombuffer(data, np.uint8)
                sums = np.zeros(len(x) + 1, dtype=tk.U)
                np.cumsum(tk.BYTE_HASH[x] * tk.powers(tk.BASE, len(x)), out=sums[1:])
                back = tk.powers(tk.BASE_INVERSE, len(x) + 1)
                q = np.arange(at // width + 1)
                s = at - width * q
                low, high = np.maximum(0, s - width + 1), np.minimum(count - 1, s)
                q, s, low, high = (y[low <= high] for y in (q, s, low, high))
                shared = (sums[s + span - width + 1] - sums[s]) * back[s]
                key = tk.mix(tk.mix(shared, 41) + q.astype(tk.U) * tk.U(tk.BASE) + tk.U(grp % (1 << 64)), width).view(np.int64)
                out += [
                    (k, role, doc, th, first + a, b - a + 1, at - a, data[a : b + span], None)
                    for k, a, b in zip(key.tolist(), low.tolist(), high.tolist(), strict=True)
                ]
            yield piece_batch(out)

    return deal


def repeated_spans(docs: DataFrame, span: int = 200) -> DataFrame:
    """(id, th, s, e): byte ranges whose span-byte strings all stand elsewhere too; ranges may overlap."""
    ship("nodeflux.llm.textkit", "nodeflux.llm.substrings")
    n = partitions(docs)
    text = F.coalesce(F.col("text"), F.lit(""))
    texts = docs.select(row_id(F.col("doc_id")).alias("id"), F.xxhash64(text).alias("th"), text.alias("text"))
    found = cut(texts.mapInArrow(anchor_reader(span), ANCHORS), "bwt-anchors")
    pairs = found.select(F.explode(F.arrays_zip("anchor", "whole")).alias("x")).select("x.anchor", "x.whole")
    counts = cut(pairs.groupBy("anchor", "whole").agg(F.count("*").alias("copies")), "bwt-counts")
    shared = counts.groupBy("anchor").agg(F.sum("copies").alias("all"), F.count("*").alias("kinds"), F.min("copies").alias("least")).filter("all > 1")
    known = cut(counts.join(shared, "anchor").select("anchor", "whole", "copies", "kinds", "least"), "bwt-shared")
    placed = (
        found.select("id", "th", F.explode(F.arrays_zip("anchor", "whole", "first", "count")).alias("x"))
        .select("id", "th", "x.anchor", "x.whole", "x.first", "x.count")
        .join(known, ["anchor", "whole"])
    )
    placed = cut(placed, "bwt-placed")
    for table in (found, counts, known):
        discard(table)
    # the first and the last place of each kind; of an anchor that has kinds seen once, the first place is open, too
    place = F.struct("id", "th", "first")
    kinds = placed.groupBy("anchor", "whole").agg(
        F.min(place).alias("a"), F.max(place).alias("b"), F.first("count").alias("count"), F.first("copies").alias("copies"),
        F.first("kinds").alias("kinds"), F.first("least").alias("least"),
    )
    pick = lambda at, grp, role: F.struct(
        F.col(f"{at}.id").alias("id"), F.col(f"{at}.th").alias("th"), grp.alias("grp"), F.lit(role).alias("role"), F.col(f"{at}.first").alias("first"),
        "count", "anchor", "whole",
    )
    run = F.xxhash64("a.id", "a.th", "b.id", "b.th", F.col("b.first") - F.col("a.first"))
    none = F.array().cast("array<struct<id:bigint,th:bigint,grp:bigint,role:int,first:int,count:int,anchor:bigint,whole:bigint>>")
    picks = kinds.select(F.inline(F.concat(
        F.when(F.col("copies") > 1, F.array(pick("a", run, FIRST), pick("b", run, LAST))).otherwise(none),
        F.when((F.col("least") == 1) & (F.col("kinds") > 1), F.array(pick("a", F.col("anchor"), OPEN))).otherwise(none),
    )))
    picks = picks.groupBy("id", "th").agg(F.collect_list(F.struct("grp", "role", "first", "count", "anchor", "whole")).alias("picks"))
    once = texts.join(picks, ["id", "th"]).dropDuplicates(["id", "th"])
    pieces = cut(once.mapInArrow(piece_reader(span), PIECES), "bwt-pieces")
    open_, both = pieces.filter(F.col("role") == OPEN), pieces.filter(F.col("role") != OPEN)
    spans = []
    for width in WIDTHS:
        hot = cut(open_.groupBy("grp").count().filter(F.col("count") > GROUP_STRETCHES).select("grp"), "bwt-hot")
        if hot.isEmpty():
            break
        spans.append(open_.join(hot, "grp", "left_anti"))
        dealt = cut(open_.join(hot, "grp", "left_semi").select(*pieces.columns).mapInArrow(closer(span, width), PIECES), "bwt-closer")
        open_ = cut(dealt.join(dealt.groupBy("grp").count().filter("count > 1").select("grp"), "grp", "left_semi").select(*pieces.columns), "bwt-alive")
        discard(dealt)
    else:  # groups are whole strings now: each is a kind
        ends = F.struct("id", "th", "first", "data")
        twice = open_.groupBy("grp").agg(F.min(ends).alias("a"), F.max(ends).alias("b"))
        kind = F.array(F.struct(F.col("x.first").alias("first"), F.lit(1).alias("count"), F.col("grp").alias("anchor"), F.lit(0).cast("long").alias("whole")))
        strings = twice.select("grp", F.posexplode(F.array("a", "b")).alias("role", "x")).select(
            "grp", "role", "x.id", "x.th", "x.first", F.lit(1).alias("count"), F.lit(0).alias("place"), "x.data",
            F.when(F.col("role") == FIRST, kind).alias("kinds"),
        )
        equal = strings.repartition(n, "grp").sortWithinPartitions("grp").mapInArrow(confirmer(span), "anchor long, whole long")
        spans_of_strings = open_.join(equal.select(F.col("anchor").alias("grp")), "grp").select("id", "th", F.col("first").alias("s"), (F.col("first") + span).alias("e"))
        open_ = None
    if open_ is not None:
        spans.append(open_)
    merged = None
    for part in spans:
        merged = part.select(*pieces.columns) if merged is None else merged.unionByName(part.select(*pieces.columns))
    out = merged.repartition(n, "grp").sortWithinPartitions("grp").mapInArrow(resolver(span), SPANS)
    if open_ is None:
        out = out.unionByName(spans_of_strings)
    certain = cut(both.repartition(n, "grp").sortWithinPartitions("grp").mapInArrow(confirmer(span), "anchor long, whole long"), "bwt-certain")
    everywhere = placed.filter("copies > 1").join(certain, ["anchor", "whole"], "left_semi")
    return out.unionByName(everywhere.select("id", "th", F.col("first").alias("s"), (F.col("first") + F.col("count") - 1 + span).alias("e")))


def cutter(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """mapInArrow: texts with sorted spans to the bytes that stay."""
    for batch in batches:
        buf, bounds = tk.raw(batch.column("text"))
        spans = batch.column("spans").to_pylist()
        removed, n_spans, kept = [], [], []
        for i, own in enumerate(spans):
            data, runs = buf[bounds[i] : bounds[i + 1]], []
            for x in own or []:
                if runs and x["s"] <= runs[-1][1]:
                    runs[-1][1] = max(runs[-1][1], x["e"])
                else:
                    runs.append([x["s"], x["e"]])
            stay = np.ones(len(data), dtype=bool)
            for s, e in runs:
                stay[s:e] = False
            kept.append(data[stay].tobytes())
            removed.append(int(len(data) - stay.sum()))
            n_spans.append(len(runs))
        yield pa.RecordBatch.from_arrays(
            [batch.column("doc_id"), tk.longs(np.diff(bounds)), pa.array(removed, pa.int64()), pa.array(n_spans, pa.int64()), pa.array(kept, pa.binary())],
            ["doc_id", "n_bytes", "n_removed", "n_spans", "kept"],
        )


def remove_repeats(docs: DataFrame, span: int = 200) -> DataFrame:
    """(doc_id, n_bytes, n_removed, n_spans, kept): kept is binary, as a cut may split a character."""
    spans = repeated_spans(docs, span).groupBy("id", "th").agg(F.sort_array(F.collect_list(F.struct("s", "e"))).alias("spans"))
    text = F.coalesce(F.col("text"), F.lit(""))
    keyed = docs.select("doc_id", text.alias("text"), row_id(F.col("doc_id")).alias("id"), F.xxhash64(text).alias("th"))
    kind = docs.schema["doc_id"].dataType.simpleString()
    return keyed.join(spans, ["id", "th"], "left").select("doc_id", "text", "spans").mapInArrow(
        cutter, f"doc_id {kind}, n_bytes long, n_removed long, n_spans long, kept binary"
    )


def op10_suffix_dedup(spark, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text")
    return remove_repeats(docs, 200).select("doc_id", "n_bytes", "n_removed", "n_spans", F.sha2("kept", 256).alias("kept_sha256"))
