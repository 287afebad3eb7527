"""Operators on single texts and lines: brute force, edge cases, round trips."""

from __future__ import annotations

import hashlib
import random
import re
from collections import Counter, defaultdict

import pyarrow as pa
import pytest
from pyspark.sql import functions as F

from nodeflux.llm import chat, decontaminate, linededup, rules, warc
from nodeflux.plans.storage import shared_dir

DOCS = "doc_id long, text string, n_lines long, score string, text2 string"
WHITE = " \t\n\x0b\x0c\r"
FOLD = str.maketrans("ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")
ODD = [
    (None, "null id\n" + "shared line of twenty chars"), (1, None), (2, ""), (3, "shared line of twenty chars\nown"),
    (4, "  SHARED line of twenty chars\t\nx\nshared line of twenty chars"), (5, "ÉÀ shared line of twenty chars"),
    (6, "ééà " * 30000), (7, "\n\n\n"), (8, "shared line of twenty chars"), (8, "shared line of twenty chars"), (8, "other text of the same id"),
]


def frame(spark, rows, schema=DOCS):
    return spark.createDataFrame([(*r, 7, "clash", "clash")[:5] for r in rows], schema)


def brute_lines(rows, min_chars=20, min_docs=3):
    low = -(2**63)
    held = defaultdict(set)
    for d, t in rows:
        for line in (t or "").split("\n"):
            key = line.strip(WHITE).translate(FOLD)
            if len(key) >= min_chars:
                held[key].add(low if d is None else d)
    out = []
    for d, t in rows:
        lines = (t or "").split("\n")
        gone = [
            len(k := x.strip(WHITE).translate(FOLD)) >= min_chars and len(held[k]) >= min_docs and max(held[k]) != (low if d is None else d)
            for x in lines
        ]
        out.append((d, len(lines), sum(gone), "\n".join(x for x, g in zip(lines, gone, strict=True) if not g)))
    return Counter(out)


def test_line_dedup_edge_cases(spark):
    got = linededup.dedup_lines(frame(spark, ODD)).select("doc_id", "n_lines", "n_dropped", "kept_text").collect()
    assert Counter(map(tuple, got)) == brute_lines(ODD)


def test_line_dedup_hot_line(spark, monkeypatch):
    monkeypatch.setattr(linededup, "HOT_IN_SAMPLE", 5)
    rows = [(i, f"the very same hot line here\nline number {i} is all alone") for i in range(60)]
    got = linededup.dedup_lines(frame(spark, rows)).select("doc_id", "n_lines", "n_dropped", "kept_text").collect()
    assert Counter(map(tuple, got)) == brute_lines(rows)


def test_line_dedup_empty_table(spark):
    assert linededup.dedup_lines(frame(spark, [])).count() == 0


def test_line_bitmaps_are_sparse(spark):
    rows = [(i, "\n".join(["x"] * 200 + ["a shared line of some length"])) for i in range(4)]
    bits = linededup.drop_bitmaps(frame(spark, rows)).collect()
    assert len(bits) == 3 and all(len(r.drops) == 1 and r.drops[0].word == 3 for r in bits)


def brute_measures(t):
    words = re.findall(r"[^\x20\x09-\x0D]+", t or "")
    lines = [x for x in (t or "").split("\n") if re.search(r"[^\x20\x09-\x0D]", x)]
    grams = Counter(tuple(words[i : i + 5]) for i in range(len(words) - 4))
    hit = {i + k for i in range(len(words) - 4) if grams[tuple(words[i : i + 5])] > 1 for k in range(5)}
    return (len(words), sum(map(len, words)), len(re.findall(r"[#*$%&|<>]", t or "")), len(lines) - len(set(lines)), len(hit))


RULE_TEXTS = [
    None, "", " \t ", "one two", "a b c d e " * 9, "a b c d e f a b c d e g h i j", "# * x " * 20, "A\nA\nB\n \n \nA", "é " * 40,
    "word " * 20000, "THE LOUD TEXT IS ALL IN CAPITALS HERE AND THERE", "w0 w1 w2 w3 w4 w5 w0 w1 w2 w3 w4 w9 z1 z2 z3",
]


def test_rules_measures(spark):
    rows = list(enumerate(RULE_TEXTS)) + [(3, "one two"), (None, "one two")]
    got = rules.apply_rules(frame(spark, rows)).collect()
    assert len(got) == len(rows)
    for r in got:
        assert (r.n_words, r.word_chars, r.n_symbols, r.n_dup_lines, r.n_repeat_words) == brute_measures(r.text)
        assert r.base_failed == (r.n_words < 10 or 100 * r.n_repeat_words > 20 * r.n_words)
        assert not (r.base_failed and r.kept)


def test_rules_order_does_not_change_the_verdict(spark):
    docs = frame(spark, list(enumerate(RULE_TEXTS)))
    both = []
    for order in (rules.default_rules(), rules.default_rules()[::-1]):
        both.append(rules.measure(docs).withColumn("kept", rules.cascade(order)).select("doc_id", "kept").orderBy("doc_id").collect())
    assert both[0] == both[1]


def test_rules_order_puts_the_rejecting_rule_first(spark):
    docs = frame(spark, [(i, " ".join(f"LOUD{i}x{k}" for k in range(20))) for i in range(20)])
    never, always = rules.Rule("never", F.lit(False)), rules.Rule("always", F.col("n_words") > 0)
    assert rules.order_rules(docs, [never, always])[0].name == "always"


def test_rules_empty_table(spark):
    assert rules.apply_rules(frame(spark, [])).count() == 0


def render(turns, me, narrators=("system",)):
    out, mask = "", []
    for _, who, said in turns:
        out += "<|assistant|>\n" if who == me else f"<|{who}|>\n" if who in narrators else f"<|user:{who}|>\n"
        if who == me:
            mask.append((len(out), len(said) + 8))
        out += said + "<|end|>\n"
    return out, mask


def test_chat_rotation(spark):
    rows = [(1, 0, "system", "be kind"), (1, 1, "ann", "hi é"), (1, 2, "bob", "ho <|end|>"), (1, 3, "ann", None), (2, 0, "ann", ""),
            (3, None, None, "who"), (None, 0, "x", "a"), (None, 0, "x", "a"), (4, 0, "system", "alone")]
    turns = spark.createDataFrame(rows, "conv_id long, turn long, role string, text string").withColumn("block", F.lit("clash"))
    got = {(r.conv_id, r.perspective): r for r in chat.rotate(turns).collect()}
    assert set(got) == {(1, "ann"), (1, "bob"), (2, "ann"), (3, "unknown"), (None, "x")}
    said = [(0, "system", "be kind"), (1, "ann", "hi é"), (2, "bob", "ho < |end|>"), (3, "ann", "")]
    for me in ("ann", "bob"):
        text, mask = render(said, me)
        assert got[1, me].rendered == text
        assert [tuple(s) for s in got[1, me].mask] == mask
        assert all(text[s : s + n].endswith("<|end|>\n") for s, n in mask)
    assert got[None, "x"].n_turns == 2


def test_chat_long_conversation_comes_in_blocks(spark):
    turns = spark.range(200).selectExpr("1L as conv_id", "id as turn", "concat('p', id % 3) as role", "string(id) as text")
    got = chat.rotate(turns).collect()
    assert len(got) == 4 * 3 and sum(r.n_turns for r in got) == 3 * 200


def test_chat_blocks_make_the_whole_dialogue(spark):
    said = [(i, "system" if i in (0, 70) else f"p{i % 3}", f"é{i}") for i in range(200)]
    turns = spark.createDataFrame([(c, *m) for c in (1, None) for m in said], "conv_id long, turn long, role string, text string")
    parts = defaultdict(list)
    for r in sorted(chat.dialogues(turns).collect(), key=lambda r: r.block):
        parts[r.conv_id, r.perspective].append(r)
    assert len(parts) == 6
    for (_, me), rows in parts.items():
        text, mask = render(said, me)
        assert len(rows) == 4 and "".join(r.rendered for r in rows) == text
        assert [tuple(s) for r in rows for s in r.mask] == mask
        assert all(text[r.offset :].startswith(r.rendered) for r in rows)
    scene = ["", "<|system|>\né0<|end|>\n"] + 2 * ["<|system|>\né0<|end|>\n<|system|>\né70<|end|>\n"]
    for r in chat.with_scene(chat.rotate(turns), turns).collect():
        text, mask = render([m for m in said if m[0] // 64 == r.block], r.perspective)
        assert r.rendered == scene[r.block] + text
        assert [(s.start - len(scene[r.block]), s.length) for s in r.mask] == mask


def test_chat_empty(spark):
    assert chat.rotate(spark.createDataFrame([], "conv_id long, turn long, role string, text string")).count() == 0


def brute_leaks(docs, items, width=10):
    words = lambda t: re.findall(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+", (t or "").translate(FOLD))
    windows = defaultdict(set)
    for i, t in items:
        w = words(t)
        n = min(width, len(w))
        for k in range(len(w) - n + 1 if n else 0):
            windows[tuple(w[k : k + n])].add(i)
    sizes = {len(k) for k in windows}
    out = []
    for d, t in docs:
        w, hit, found = words(t), set(), set()
        for n in sizes:
            for k in range(len(w) - n + 1):
                if (got := windows.get(tuple(w[k : k + n]))) is not None:
                    hit |= set(range(k, k + n))
                    found |= got
        names = ",".join(sorted(map(str, found)))
        out.append((d, len(w), len(hit), len(found), hashlib.sha256(names.encode()).hexdigest(), bool(hit)))
    return Counter(out)


LONG = "alpha beta gamma delta epsilon zeta eta theta iota kappa lambda mu nu"
ITEMS = [(1, LONG), (2, "short item"), (3, None), (4, "--"), (5, LONG.upper() + " extra"), (10, "solo"), (11, "été À part"), (12, LONG)]
LEAKY = [
    (1, None), (2, ""), (3, "x " + LONG + " y"), (4, "a Short, ITEM b"), (5, LONG[:40]), (6, "été À part"), (7, "été à part"),
    (None, LONG), (8, LONG + " " + LONG), (8, LONG + " " + LONG), (9, "solo " * 5000), (10, "shortitem"), (11, LONG.replace(" ", "\n")),
]


@pytest.mark.parametrize("block_bytes", [1 << 20, 60])
def test_decontamination(spark, block_bytes):
    docs = frame(spark, LEAKY)
    items = spark.createDataFrame([(i, t, 0) for i, t in ITEMS], "item_id long, text string, spans int")
    found = decontaminate.find_leaks(docs, items, 10, block_bytes).persist()
    got = found.select(
        "doc_id", "n_words", decontaminate._hit_words(F.col("spans")), F.size("items"),
        F.sha2(F.array_join(F.array_sort(F.transform("items", lambda x: x.cast("string"))), ","), 256), F.size("spans") > 0,
    ).collect()
    want = brute_leaks(LEAKY, ITEMS)
    assert Counter(map(tuple, got)) == want
    clean = decontaminate.remove_leaks(docs, items, 10, block_bytes).collect()
    assert Counter(r.doc_id for r in clean) == Counter(d for d, *_, bad in want.elements() if not bad)


def test_decontamination_longest_match_and_empty_tables(spark):
    docs, items = frame(spark, LEAKY), spark.createDataFrame(ITEMS, "item_id long, text string")
    longest = {r.doc_id: tuple(r.longest) if r.longest else None for r in decontaminate.leak_report(docs, items).collect() if r.doc_id in (2, 3, 5, 6, 9)}
    # words, place, item and its word; seven words are no window and are told
    assert longest == {2: None, 3: (13, 1, 1, 0), 5: (7, 0, 1, 0), 6: (3, 0, 11, 0), 9: (1, 0, 10, 0)}
    assert not any(r.contaminated for r in decontaminate.leak_report(docs, items.limit(0)).collect())
    assert decontaminate.leak_report(docs.limit(0), items).count() == 0


def test_every_test_suffix_is_searched():
    """Longest matches and places of all item suffixes against a plain search, over several shards."""
    rng = random.Random(3)
    texts = [" ".join(rng.choices("abc", k=rng.randrange(0, 60))) for _ in range(12)] + ["", None]
    asked = [" ".join(rng.choices("abc", k=rng.randrange(1, 25))) for _ in range(8)]
    block = decontaminate.item_block(list(range(8)), asked, 10)
    search = decontaminate.Searcher(block, 4)
    buf, bounds = decontaminate.tk.raw(pa.array(texts, pa.large_string()))
    for a, b in ((0, 5), (5, 14)):
        part = buf[bounds[a] : bounds[b]]
        found = search.search(decontaminate.tk.words(part, bounds[a : b + 1] - bounds[a], decontaminate.tk.ALNUM), part.tobytes())
        got = {(int(search.item[q]), int(search.start[q] - block.first[search.item[q]]), d, p): n for q, d, p, n in zip(*(x.tolist() for x in found), strict=True)}
        want = {}
        for i, item in enumerate(asked):
            x = item.split()
            for s in range(len(x)):
                window = min(10, len(x)) if len(x) - s >= min(10, len(x)) else 99
                for d, t in enumerate(texts[a:b]):
                    y = (t or "").split()
                    for p in range(len(y)):
                        n = 0
                        while s + n < len(x) and p + n < len(y) and x[s + n] == y[p + n]:
                            n += 1
                        if n >= min(4, window):
                            want[i, s, d, p] = n
        assert got == want


PAGES = [
    (1, "http://a/", "x" * 1500), (2, "http://b/\r\nX-Evil: 1", "x" * 1500), (3, None, "x" * 999), (4, "u", "x" * 999), (5, "u", None), (6, "u", ""),
    (7, "u", "ends with line end\r\n"), (8, "u", "\r\n\r\nWARC/1.1\r\nWARC-Type: response\r\nContent-Length: 10\r\n\r\nmagic inside\r\n\r\n"),
    (9, "u", "é" * 2000 + "\r\n\r\n"), (10, "u", "é" * 2000 + "\r\n\r\n"), (10, "u", "é" * 2000 + "\r\n\r\n"), (11, "u", "\r\n"), (12, "u", "\r\n\r\n\r\n"),
    (None, "u", "null id"), (13, "u", "WARC/1.0\r\nContent-Length: 5"), (14, "u", "a\r\n\r\nWARC/1.1\r\nContent-Length: 3\r\n\r\nabc\r\n\r\n\r\n"),
]


@pytest.mark.parametrize("compression", ["gzip", "none"])
def test_warc_round_trip(spark, compression, tmp_path):
    pages = spark.createDataFrame([(*p, "clash") for p in PAGES], "page_id long, url string, html string, value string").coalesce(2)
    path = f"{shared_dir(spark)}/test-warc-{tmp_path.name}-{hashlib.md5(str(tmp_path).encode()).hexdigest()}"
    warc.write_warc(pages, path, compression)
    last = {}
    for i, _, t in PAGES:
        if i is not None:
            last[t or ""] = max(i, last.get(t or "", i))
    want = []
    for i, _, t in PAGES:
        data = (t or "").encode()
        revisit = len(data) >= 1000 and i is not None and i < last[t or ""]
        want.append((i, len(data), hashlib.sha1(data).hexdigest(), "revisit" if revisit else "response", last[t] if revisit else None))
    assert Counter(map(tuple, warc.read_pages(spark, path).collect())) == Counter(want)


def test_warc_small_splits(spark, tmp_path):
    """Records and payloads that cross the splits of a plain archive."""
    before = spark.conf.get("spark.sql.files.maxPartitionBytes")
    spark.conf.set("spark.sql.files.maxPartitionBytes", "700")
    try:
        pages = spark.createDataFrame(PAGES, "page_id long, url string, html string").coalesce(1)
        path = f"{shared_dir(spark)}/test-warc-{hashlib.md5(str(tmp_path).encode()).hexdigest()}-s"
        warc.write_warc(pages, path, "none")
        assert Counter(r.page_id for r in warc.read_pages(spark, path).collect()) == Counter(p[0] for p in PAGES)
    finally:
        spark.conf.set("spark.sql.files.maxPartitionBytes", before)


def test_warc_empty(spark, tmp_path):
    pages = spark.createDataFrame([], "page_id long, url string, html string")
    path = f"{shared_dir(spark)}/test-warc-{hashlib.md5(str(tmp_path).encode()).hexdigest()}-e"
    warc.write_warc(pages, path)
    assert warc.read_pages(spark, path).count() == 0


def test_leaks_of_items_without_id(spark):
    words = [" ".join(f"w{i}x{j}" for j in range(12)) for i in range(3)]
    docs = spark.createDataFrame([(0, f"a {words[0]} b {words[1]}"), (1, words[2]), (2, "nothing here")], "doc_id long, text string")
    items = spark.createDataFrame([(7, words[0]), (None, words[1]), (None, words[2])], "item_id long, text string")
    got = {r.doc_id: r for r in decontaminate.leak_report(docs, items).collect()}
    assert [got[d].contaminated for d in range(3)] == [True, True, False]
    assert [(got[d].n_hit, got[d].n_items) for d in range(3)] == [(24, 2), (12, 1), (0, 0)]
    assert got[1].items_sha256 == got[2].items_sha256 != got[0].items_sha256
    assert [r.doc_id for r in decontaminate.remove_leaks(docs, items, block_bytes=1).collect()] == [2]
    two = decontaminate.find_leaks(docs, items, block_bytes=1).filter("doc_id = 0").first()
    assert two["items"] == [7, None]
    import duckdb

    con = duckdb.connect()
    con.register("documents", docs.toPandas())
    con.register("benchmark", items.toPandas().astype({"item_id": "Int64"}))
    want = {r[0]: r[1:] for r in con.execute(decontaminate.OP2_SQL).fetchall()}
    for d, r in got.items():
        assert want[d] == (r.n_words, r.n_hit, r.n_items, r.items_sha256, r.contaminated)


def test_warc_reads_bytes_that_are_no_text(spark, tmp_path):
    """An archive from elsewhere, with payloads in other encodings: offsets count bytes, so the chain holds."""
    bodies = [b"\xff\xfe caf\xe9 \x80" * 40, "é".encode() * 7, b"\r\n\r\n\xe9WARC/1.1\r\n", b""]
    data = b""
    for i, body in enumerate(bodies):
        block = b"HTTP/1.1 200 OK\r\n\r\n" + body
        data += b"WARC/1.0\r\nWARC-Type: response\r\nX-Page-Id: %d\r\nContent-Length: %d\r\n\r\n" % (i, len(block)) + block + b"\r\n\r\n"
    (tmp_path / "one.warc").write_bytes(data)
    got = warc.read_warc(spark, f"file://{tmp_path}/one.warc").select("page_id", F.col("payload").cast("binary").alias("payload")).collect()
    assert sorted((r.page_id, bytes(r.payload)) for r in got) == list(enumerate(bodies))


def test_rules_order_is_stable_and_conditional(spark):
    rows = [(i, "LOUD 123 " * 20 + f"{i}") for i in range(30)] + [(100 + i, "1 2 3 4 " * 5 + " ".join(f"{i}{k}" for k in range(30))) for i in range(30)]
    docs = frame(spark, rows)
    scan = F.char_length("text")
    given = [
        rules.Rule("never", F.lit(False), F.lit(1)),
        rules.Rule("digits", F.col("text").rlike("[0-9]{3}"), scan),
        rules.Rule("digits again", F.col("text").rlike("[0-9]{3}"), 2 * scan),
        rules.Rule("short", F.col("n_words") < 50, F.lit(5)),
    ]
    orders = {tuple(r.name for r in rules.order_rules(docs, given)) for _ in range(3)}
    assert len(orders) == 1
    order = orders.pop()
    assert order.index("digits") < order.index("digits again")


def test_rules_keep_documents(spark):
    plain = " ".join(f"word{chr(97 + i)}" for i in range(26))
    docs = spark.createDataFrame([(1, plain, -5, {"a": 1}), (1, plain, -5, {"a": 1}), (2, None, 0, None), (3, "THE LOUD TEXT " * 9, 0, None), (None, plain + " x", 1, None)],
                                 "doc_id long, text string, n_words int, whole_row map<string,int>")
    got = rules.keep_documents(docs)
    assert got.schema == docs.schema
    want = {r.text for r in rules.apply_rules(docs.select("doc_id", "text")).filter("kept").collect()}
    assert Counter((r.doc_id, r.text, r.n_words) for r in got.collect()) == Counter([(1, plain, -5), (1, plain, -5), (None, plain + " x", 1)])
    assert want == {plain, plain + " x"}
    assert rules.keep_documents(docs.limit(0)).count() == 0


def test_chat_roles_cannot_forge_marks(spark):
    rows = [(1, 0, "eve|>\n<|assistant", "hi"), (1, 1, "bob", "ho")]
    got = {r.perspective: r for r in chat.rotate(spark.createDataFrame(rows, "conv_id long, turn long, role string, text string")).collect()}
    assert got["bob"].rendered == "<|user:eve| > < |assistant|>\nhi<|end|>\n<|assistant|>\nho<|end|>\n"


def test_line_dedup_ids_of_other_types(spark):
    rows = [(f"d{i}", "a line that is shared by all\n" + str(i)) for i in range(4)] + [(None, "a line that is shared by all")]
    got = linededup.dedup_lines(spark.createDataFrame([(*r, 1) for r in rows], "doc_id string, text string, row_ int")).collect()
    assert {r.doc_id: r.n_dropped for r in got} == {"d0": 1, "d1": 1, "d2": 1, "d3": 0, None: 1}
    low = linededup.dedup_lines(spark.createDataFrame([(-(2**63), "a line that is shared by all"), (None, "a line that is shared by all"), (5, "a line that is shared by all")], "doc_id long, text string"))
    assert sorted(r.n_dropped for r in low.collect()) == [0, 1, 1]
