"""Benchmark decontamination with suffix arrays of the training texts.

A task turns its documents into word sequences, shard by shard, and sorts the suffixes that
start with an item's word (no other can match one). Every suffix of every item is then
binary-searched in the array, word by word: the interval of the suffixes that share its first
words shrinks until it is empty, which gives its longest verbatim match and all places, and
at the depth of a window all occurrences of that. Documents are whole in their task, so
nothing is shuffled; items are sent to the tasks in blocks of bounded size, one pass over the
documents for each block.

A window has `width` consecutive item words; an item of fewer words is one window. Matches of
`shortest` words or more are told, window or not. Words are compared as text: 64-bit word
hashes lead to a match, and the words' bytes confirm it.

Defined results: null and empty texts have no words and hit nothing; an item without words
has no window; equal windows count for every item that has them; repeated ids give a row
each; items with a null item_id hit as others do, count as one item together and have no name
in items_sha256; a null doc_id stays null; an empty benchmark leaves all documents clean; of
equally long matches the first in the text is told, of its items' words the first; other
columns of either table play no part.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from . import textkit as tk
from .common import ship

WIDTH = 10
#: Bytes of item texts in a block; a larger benchmark takes several passes.
BLOCK_BYTES = 32 << 20
#: Words of a match that is told though it holds no window.
SHORTEST = 5


@dataclass
class Items:
    """One block of items as words: what the tasks get."""

    ids: list[int | None]
    #: hashes and bytes of the words of item i: first[i] .. first[i + 1]
    first: np.ndarray
    hashes: np.ndarray
    text: list[bytes]
    width: int


def item_block(ids: list[int | None], texts: list[str | None], width: int) -> Items:
    buf, bounds = tk.raw(pa.array(texts, pa.large_string()))
    w = tk.words(buf, bounds, tk.ALNUM)
    folded = tk.FOLD[buf].tobytes()
    return Items(ids, w.first, w.hashes, [folded[s:e] for s, e in zip(w.starts.tolist(), w.ends.tolist(), strict=True)], width)


def suffix_order(words: np.ndarray, use: np.ndarray, depth: int) -> np.ndarray:
    """The places marked by `use`, in order of their suffixes' first `depth` words; ranks are doubled."""
    order = np.argsort(words)
    ordered = words[order]
    rank = np.empty(len(words), dtype=np.int64)
    rank[order] = np.cumsum(np.concatenate(([0], (ordered[1:] != ordered[:-1]).astype(np.int64))))
    have = 1
    while have < depth:
        after = np.zeros(len(rank), dtype=np.int64)
        after[:-have] = rank[have:] + 1
        key = rank * (len(rank) + 1) + after
        order = np.argsort(key)
        ordered = key[order]
        new = ordered[1:] != ordered[:-1]
        rank[order] = np.cumsum(np.concatenate(([0], new.astype(np.int64))))
        if new.all():
            break
        have *= 2
    at = np.flatnonzero(use)
    return at[np.argsort(rank[at], kind="stable")]


class Searcher:
    """Binary-searches a block's suffixes in one shard after another."""

    def __init__(self, items: Items, shortest: int | None = SHORTEST) -> None:
        self.items = items
        n = np.diff(items.first)
        #: of every test suffix: its item, first word, words, words of the window that it starts (0: none), words worth telling
        self.item = np.repeat(np.arange(len(n)), n)
        self.start = np.arange(len(items.hashes))
        self.words = items.first[1:][self.item] - self.start
        window = np.minimum(items.width, n)[self.item]
        self.window = np.where(self.words >= window, window, 0)
        told = np.full(len(window), np.iinfo(np.int64).max if shortest is None else shortest)
        self.told = np.where(self.window > 0, np.minimum(told, self.window), told)
        use = self.words >= self.told
        self.item, self.start, self.words, self.window, self.told = (x[use] for x in (self.item, self.start, self.words, self.window, self.told))
        self.longest = int(self.words.max(initial=0))
        self.vocabulary = np.unique(items.hashes[self.start])

    def search(self, w: tk.Words, folded: bytes) -> tuple[np.ndarray, ...]:
        """(test suffix, document, word of the document, matching words) of all matches that are worth telling."""
        none = np.zeros(0, np.int64)
        if not len(w.starts) or not len(self.item):
            return none, none, none, none
        n_docs = len(w.first) - 1
        doc = np.repeat(np.arange(n_docs), np.diff(w.first))
        place = np.arange(len(doc)) + doc  # a document ends with a zero that no word equals
        seq = np.zeros(len(doc) + n_docs, dtype=tk.U)
        seq[place] = w.hashes
        use = np.zeros(len(seq), dtype=bool)
        use[place] = self.vocabulary[np.minimum(np.searchsorted(self.vocabulary, w.hashes), len(self.vocabulary) - 1)] == w.hashes
        array = suffix_order(seq, use, self.longest)
        seq = np.concatenate((seq, np.zeros(self.longest + 1, tk.U)))
        first = seq[array]
        asked = self.items.hashes[self.start]
        q = np.arange(len(asked))
        lo, hi = np.searchsorted(first, asked), np.searchsorted(first, asked, side="right")
        out = []
        for depth in range(1, self.longest + 1):  # all places in [lo, hi) share the first `depth` words of suffix q
            there = lo < hi
            q, lo, hi = q[there], lo[there], hi[there]
            if not len(q):
                break
            more = self.words[q] > depth
            word = self.items.hashes[np.where(more, self.start[q] + depth, 0)]
            low = self.bound(seq, array, lo, np.where(more, hi, lo), depth, word, False)
            high = self.bound(seq, array, low, np.where(more, hi, low), depth, word, True)
            told = depth >= self.told[q]
            for a, b in ((lo, low), (high, hi)):  # these part here
                count = np.where(told, b - a, 0)
                of = np.repeat(np.arange(len(q)), count)
                at = np.arange(len(of)) - np.repeat(np.cumsum(count) - count, count) + a[of]
                out.append((q[of], array[at], np.full(len(of), depth)))
            lo, hi = low, high
        if not out:
            return none, none, none, none
        suffix, at, length = (np.concatenate(x) for x in zip(*out, strict=True))
        d = np.searchsorted(w.first + np.arange(n_docs + 1), at, side="right") - 1
        word = at - d
        right = [
            all(folded[w.starts[p + k] : w.ends[p + k]] == self.items.text[s + k] for k in range(n))
            for p, s, n in zip(word.tolist(), self.start[suffix].tolist(), length.tolist(), strict=True)
        ]
        return suffix[right], d[right], (word - w.first[d])[right], length[right]

    @staticmethod
    def bound(seq: np.ndarray, array: np.ndarray, lo: np.ndarray, hi: np.ndarray, depth: int, word: np.ndarray, right: bool) -> np.ndarray:
        """For each interval the first place whose word at `depth` is not below (right: is beyond) the asked one."""
        lo, hi = lo.copy(), hi.copy()
        live = np.flatnonzero(lo < hi)
        while len(live):
            mid = (lo[live] + hi[live]) >> 1
            x = seq[array[mid] + depth]
            below = x <= word[live] if right else x < word[live]
            lo[live[below]] = mid[below] + 1
            hi[live[~below]] = mid[~below]
            live = live[lo[live] < hi[live]]
        return lo


LONGEST = "struct<words:bigint,at:bigint,item:bigint,item_word:bigint>"
MATCHES = f"doc_id long, n_words long, spans array<struct<s:long,e:long>>, items array<long>, longest {LONGEST}, text string"


def matcher(block, last: bool):
    """mapInArrow: (doc_id, text) to the hit spans and the items of each document.

    A pass over another block adds to what earlier passes found; the last one drops the text.
    """

    def match(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        search = Searcher(block.value)
        span = pa.struct([("s", pa.int64()), ("e", pa.int64())])
        best = pa.struct([(c, pa.int64()) for c in ("words", "at", "item", "item_word")])
        for batch in batches:
            buf, bounds = tk.raw(batch.column("text"))
            for a, b in tk.runs(bounds):
                part = buf[bounds[a] : bounds[b]]
                w = tk.words(part, bounds[a : b + 1] - bounds[a], tk.ALNUM)
                spans: list[list[dict]] = [[] for _ in range(a, b)]
                items: list[set[int | None]] = [set() for _ in range(a, b)]
                longest: list[dict | None] = [None] * (b - a)
                if "spans" in batch.schema.names:
                    before = batch.slice(a, b - a)
                    items = [set(x) for x in before.column("items").to_pylist()]
                    longest = before.column("longest").to_pylist()
                found = search.search(w, tk.FOLD[part].tobytes())
                order = np.lexsort((found[0], found[2], found[1]))
                for q, d, s, n in zip(*(x[order].tolist() for x in found), strict=True):
                    item, size = int(search.item[q]), int(search.window[q])
                    if longest[d] is None or n > longest[d]["words"]:
                        word = int(search.start[q] - search.items.first[item])
                        longest[d] = {"words": n, "at": s, "item": search.items.ids[item], "item_word": word}
                    if not size or n < size:
                        continue
                    if spans[d] and spans[d][-1]["e"] >= s:
                        spans[d][-1]["e"] = max(spans[d][-1]["e"], s + size)
                    else:
                        spans[d].append({"s": s, "e": s + size})
                    items[d].add(search.items.ids[item])
                if "spans" in batch.schema.names:
                    spans = [x + y for x, y in zip(before.column("spans").to_pylist(), spans, strict=True)]
                yield pa.RecordBatch.from_arrays(
                    [
                        batch.column("doc_id").slice(a, b - a).cast(pa.int64()),
                        tk.longs(np.diff(w.first)),
                        pa.array(spans, pa.list_(span)),
                        pa.array([sorted(x, key=lambda i: (i is None, i or 0)) for x in items], pa.list_(pa.int64())),
                        pa.array(longest, best),
                        pa.nulls(b - a, pa.string()) if last else batch.column("text").slice(a, b - a),
                    ],
                    ["doc_id", "n_words", "spans", "items", "longest", "text"],
                )

    return match


def item_blocks(benchmark: DataFrame, width: int, block_bytes: int) -> Iterator[Items]:
    """Blocks of items of at most about block_bytes; the driver holds one at a time."""
    items = benchmark.filter("text is not null").select(F.col("item_id").cast("long").alias("item_id"), "text")
    held, size = [], 0
    for row in items.toLocalIterator():
        held.append(row)
        size += len(row.text)
        if size >= block_bytes:
            yield item_block([r.item_id for r in held], [r.text for r in held], width)
            held, size = [], 0
    if held:
        yield item_block([r.item_id for r in held], [r.text for r in held], width)


def _hit_words(spans: Column) -> Column:
    """Words in the union of spans."""
    end = F.aggregate(
        F.array_sort(spans),
        F.struct(F.lit(0).cast("long").alias("sum"), F.lit(0).cast("long").alias("upto")),
        lambda acc, x: F.struct(
            (acc["sum"] + F.greatest(F.lit(0).cast("long"), x["e"] - F.greatest(x["s"], acc["upto"]))).alias("sum"),
            F.greatest(acc["upto"], x["e"]).alias("upto"),
        ),
    )
    return end["sum"]


def find_leaks(docs: DataFrame, benchmark: DataFrame, width: int = WIDTH, block_bytes: int = BLOCK_BYTES) -> DataFrame:
    """(doc_id, n_words, spans, items, longest): hit word spans, items and the longest match of each document and where it is, or null."""
    ship("nodeflux.llm.textkit", "nodeflux.llm.decontaminate")
    spark = docs.sparkSession
    texts = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text")
    blocks = item_blocks(benchmark, width, block_bytes)
    block = next(blocks, item_block([], [], width))
    while block is not None:
        following = next(blocks, None)
        texts = texts.mapInArrow(matcher(spark.sparkContext.broadcast(block), following is None), MATCHES)
        block = following
    return texts.drop("text")


def leak_report(docs: DataFrame, benchmark: DataFrame, width: int = WIDTH) -> DataFrame:
    """(doc_id, n_words, n_hit, n_items, items_sha256, contaminated, longest)."""
    found = find_leaks(docs, benchmark, width)
    names = F.array_join(F.array_sort(F.transform("items", lambda x: x.cast("string"))), ",")
    return found.select(
        "doc_id",
        "n_words",
        _hit_words(F.col("spans")).alias("n_hit"),
        F.size("items").cast("long").alias("n_items"),
        F.sha2(names, 256).alias("items_sha256"),
        (F.size("spans") > 0).alias("contaminated"),
        "longest",
    )


def clean_filter(block):
    """mapInArrow: the rows whose text holds no window of the block."""

    def keep(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        search = Searcher(block.value, None)
        for batch in batches:
            buf, bounds = tk.raw(batch.column("text"))
            clean = np.ones(batch.num_rows, dtype=bool)
            for a, b in tk.runs(bounds):
                part = buf[bounds[a] : bounds[b]]
                w = tk.words(part, bounds[a : b + 1] - bounds[a], tk.ALNUM)
                clean[a + search.search(w, tk.FOLD[part].tobytes())[1]] = False
            yield batch.filter(pa.array(clean))

    return keep


def remove_leaks(docs: DataFrame, benchmark: DataFrame, width: int = WIDTH, block_bytes: int = BLOCK_BYTES) -> DataFrame:
    """docs without the documents that hold a window of an item; nothing is shuffled.

    Null and empty texts, null ids and repeated rows stay as they are; columns of any name stay.
    """
    ship("nodeflux.llm.textkit", "nodeflux.llm.decontaminate")
    for block in item_blocks(benchmark, width, block_bytes):
        docs = docs.mapInArrow(clean_filter(docs.sparkSession.sparkContext.broadcast(block)), docs.schema)
    return docs


def op2_decontamination(spark, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text")
    items = spark.read.parquet(f"{sf_dir}/benchmark.parquet").select("item_id", "text")
    return leak_report(docs, items).drop("longest")


def duck_words(column: str) -> str:
    folded = f"translate(coalesce({column}, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz')"
    return rf"regexp_extract_all({folded}, '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+')"


OP2_SQL = f"""
WITH d AS (SELECT doc_id, {duck_words("text")} AS w FROM documents),
b AS (SELECT item_id, {duck_words("text")} AS w FROM benchmark),
q AS (
  SELECT DISTINCT item_id, size, array_to_string(w[i:i+size-1], ' ') AS win
  FROM (SELECT item_id, w, size, unnest(range(1, len(w) - size + 2)) AS i
        FROM (SELECT *, least(10, len(w)) AS size FROM b WHERE len(w) > 0))
), sizes AS (SELECT DISTINCT size FROM q),
p AS (
  SELECT doc_id, size, i, array_to_string(w[i:i+size-1], ' ') AS win
  FROM (SELECT doc_id, w, size, unnest(range(1, len(w) - size + 2)) AS i FROM d, sizes WHERE len(w) >= size)
), hits AS (SELECT doc_id, item_id, i, p.size FROM p JOIN q ON p.win = q.win AND p.size = q.size),
covered AS (SELECT doc_id, count(DISTINCT pos) AS n_hit FROM (SELECT doc_id, unnest(range(i, i + size)) AS pos FROM hits) GROUP BY doc_id),
found AS (
  SELECT doc_id, count(*) AS n_items, string_agg(item_id::VARCHAR, ',' ORDER BY item_id::VARCHAR) AS ids
  FROM (SELECT DISTINCT doc_id, item_id FROM hits) GROUP BY doc_id
)
SELECT d.doc_id, len(w) AS n_words, coalesce(n_hit, 0) AS n_hit, coalesce(n_items, 0) AS n_items,
       sha256(coalesce(ids, '')) AS items_sha256, coalesce(n_hit, 0) > 0 AS contaminated
FROM d LEFT JOIN covered USING (doc_id) LEFT JOIN found USING (doc_id)
"""
