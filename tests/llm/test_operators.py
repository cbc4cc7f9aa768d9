"""The ten operators against brute force, exact round trips and held-out accuracy, and their odd cases."""

import hashlib
import html
import io
import re
import zipfile
import zlib

import numpy as np
import pyarrow as pa
import pyarrow.parquet as pq
import pytest
import xxhash
from pyspark.sql import functions as F

from edgesplit.llm import html_text, mixing, near_vectors, nearest, packing, quality, sharding, simhash, substring, warc_zip
from edgesplit.llm import words as W
from edgesplit.llm.queries import ORACLES, QUERIES, vocabulary

SF = "/root/testdata/sf0.001"
SCHEMA = "doc_id long, text string, lang string, source string, n_chars long"
LONG = " ".join(f"w{i}" for i in range(4000))
ODD = [
    (1, None, "en", "a", None), (2, "", "en", None, 0), (3, "one two", None, "a", 7), (4, "one two", "en", "b", 7), (5, LONG, "en", "b", 1), (6, LONG + " end", "en", "c", 1),
    (7, " \n\t ", "en", "a", 4), (3, "one two", None, "a", 7), (None, "no id here at all", "de", "b", 3), (8, "Ünïcödé  straße x", "de", "", 9),
]


@pytest.fixture(scope="module")
def odd(spark):
    return spark.createDataFrame(ODD, SCHEMA).withColumn("shard", F.lit("clash")).withColumn("n_words", F.lit(-1)).withColumn("taken", F.lit("x")).withColumn("start", F.lit(0.5))


@pytest.fixture(scope="module")
def empty(odd):
    return odd.limit(0)


@pytest.fixture(scope="module")
def docs(spark):
    return spark.read.parquet(f"{SF}/documents.parquet")


def test_words_split_as_bytes_do():
    texts = ["a b", None, "", "  x\ty\x0bz\r\n", "é ß q", "end", "start"]
    w = W.split(pa.array(texts))
    raw = w.data.tobytes()
    got = [[raw[b:e] for b, e in zip(w.begins[i:j], w.ends[i:j], strict=True)] for i, j in zip(w.first[:-1], w.first[1:], strict=True)]
    assert got == [(t or "").encode().split() for t in texts]
    h = W.hashes(w)
    assert len(set(h.tolist())) == len({x for t in got for x in t})


# ---- 1 -------------------------------------------------------------------------------------------


def plain_print(text, n=3):
    w = (text or "").encode().lower().split()
    s = [b" ".join(w[i : i + n]) for i in range(len(w) - n + 1)] if len(w) >= n else ([b" ".join(w)] if w else [])
    bits = [sum(xxhash.xxh64_intdigest(x, 42) >> b & 1 for x in s) for b in range(64)]
    return sum(1 << b for b, c in enumerate(bits) if 2 * c > len(s))


def plain_components(prints, reach):
    ids = sorted(prints)
    up = {i: i for i in ids}

    def root(x):
        while up[x] != x:
            x = up[x]
        return x

    for i, a in enumerate(ids):
        for b in ids[i + 1 :]:
            if (prints[a] ^ prints[b]).bit_count() <= reach:
                x, y = root(a), root(b)
                up[max(x, y)] = min(x, y)
    return {i: root(i) for i in ids}


def test_simhash_brute_force(spark, docs):
    got = {r["doc_id"]: (r["fingerprint"], r["component_id"]) for r in QUERIES["op1_simhash"](spark, SF).collect()}
    prints = {r["doc_id"]: plain_print(r["text"]) for r in docs.collect()}
    assert {i: int(f, 16) for i, (f, _) in got.items()} == prints
    assert {i: c for i, (_, c) in got.items()} == plain_components(prints, 2)


def test_links_of_large_buckets(spark):
    draw = np.random.default_rng(1)
    base = int(draw.integers(0, 1 << 62))
    prints = {base ^ sum(1 << int(b) for b in draw.choice(26, n, replace=False)) for n in (0, 1, 2, 3, 4, 9) for _ in range(40)} | {int(x) for x in draw.integers(0, 1 << 63, 50)}
    rows = spark.createDataFrame([(x - (1 << 64) if x >> 63 else x,) for x in prints], "fp long")
    edges = [(r["a"] % (1 << 64), r["b"] % (1 << 64)) for r in simhash.link_edges(rows, 2, max_paired=8).collect()]
    assert all((a ^ b).bit_count() <= 2 for a, b in edges)
    want = plain_components({x: x for x in prints}, 2)
    up = {x: x for x in prints}

    def root(x):
        while up[x] != x:
            x = up[x]
        return x

    for a, b in edges:
        up[max(root(a), root(b))] = min(root(a), root(b))
    assert {x: root(x) for x in prints} == want


def test_pivots_discard_and_lose_nothing():
    draw = np.random.default_rng(6)
    fps = draw.integers(0, 1 << 64, 400, dtype=np.uint64)
    near = fps ^ (np.uint64(1) << draw.integers(0, 64, 400, dtype=np.uint64)) ^ (np.uint64(1) << draw.integers(0, 64, 400, dtype=np.uint64))
    pivots = simhash.Pivots(2)
    assert (np.abs(pivots.far_table(fps) - pivots.far_table(near)) <= 2).all()
    # Some choice of groups puts both in one bucket, at every depth.
    for free in ((1 << 64) - 1, sum(1 << x for x in range(3, 40)), 0b1011010):
        inside = [(a, b) for a, b in zip(fps.tolist(), near.tolist(), strict=True) if not (a ^ b) & ~free]
        for a, b in inside:
            one, two = (dict((bits, int(k[0])) for bits, k in pivots.keys(np.array([x], np.uint64), free)) for x in (a, b))
            assert any(one[bits] == two[bits] for bits in one)
    # A group table holds as much as the bits do.
    bits = sum(1 << x for x in range(5, 18))
    tables, values = pivots.group_table(fps, bits), fps & np.uint64(bits)
    assert len({t.tobytes() for t in tables}) == len(set(values.tolist())) == len({(t.tobytes(), v) for t, v in zip(tables, values.tolist(), strict=True)})


def test_far_table_discards_most_pairs(spark):
    """Fingerprints that share 40 bits fall into common buckets; the far table keeps few of their pairs from verification."""
    draw = np.random.default_rng(7)
    base = int(draw.integers(0, 1 << 62))
    prints = {base ^ int(x) for x in draw.integers(0, 1 << 24, 600)}
    rows = spark.createDataFrame([(x - (1 << 64) if x >> 63 else x,) for x in prints], "fp long")
    counts = simhash.pivot_counts(rows, max_paired=1000).first()
    assert counts["pairs"] == counts["discarded"] + counts["survivors"] and counts["discarded"] > 0.95 * counts["pairs"] > 1000


def test_simhash_odd_cases(odd, empty):
    rows = [tuple(r) for r in simhash.near_duplicates(odd).collect()]
    assert len(rows) == len(ODD)
    by = {r[0]: r for r in rows}
    assert by[1][1] == by[2][1] == by[7][1] == 0 and by[7][2] == 1 and by[4][2] == 3
    assert simhash.near_duplicates(empty).count() == 0


def test_near_copies_by_similarity(spark):
    draw = np.random.default_rng(4)
    texts = [[f"v{x}" for x in draw.integers(0, 5000, 250)] for _ in range(30)]
    copies = [list(t) for t in texts[:10]]
    for t in copies:
        t[int(draw.integers(0, 250))] = "changed"
    rows = [(i, " ".join(t), "en", "s", 0) for i, t in enumerate(texts + copies + [texts[20]])]
    frame = spark.createDataFrame(rows, SCHEMA)
    kept = {r["doc_id"] for r in simhash.keep_one(frame, simhash.similar_documents(frame)).collect()}
    assert kept == set(range(30))


def test_keep_one_loses_no_text(spark):
    """Rows that share a doc_id but not their text, repeated rows, and rows without a doc_id."""
    text = lambda i: " ".join(f"t{i}w{j}" for j in range(30))
    rows = [(1, text(1)), (1, text(2)), (2, text(1)), (3, text(2) + " more"), (4, text(4)), (4, text(4)), (None, text(5)), (None, text(5)), (None, text(4)), (None, text(6))]
    frame = spark.createDataFrame([(i, t, "en", "s", 0) for i, t in rows], SCHEMA).withColumn("head", F.lit("clash"))
    kept = simhash.keep_one(frame, simhash.similar_documents(frame))
    assert kept.columns == frame.columns
    assert sorted(((r["doc_id"], r["text"]) for r in kept.collect()), key=repr) == sorted([(1, text(1)), (1, text(2)), (4, text(4)), (None, text(5)), (None, text(6))], key=repr)


def test_near_copies_without_a_doc_id(spark):
    """Texts of rows without a doc_id link with named ones and with each other, in small buckets and in large ones."""
    text = lambda n, changed: " ".join(f"{n}w{i}" if i != changed else "other" for i in range(120))
    rows = [(1, text("a", -1)), (None, text("a", 60)), (None, text("b", -1)), (None, text("b", 60)), (None, text("b", 60)), (7, text("c", -1)), *((None, text("c", 3 * i)) for i in range(40)), (None, text("d", -1))]
    frame = spark.createDataFrame(rows, "doc_id long, text string")
    made = simhash.similar_documents(frame)
    roots = {}
    for r in made.select("text_key", "root").distinct().collect():
        roots.setdefault(r["root"], set()).add(r["text_key"])
    assert sorted(map(len, roots.values())) == [1, 2, 2, 41]
    kept = sorted((r["doc_id"] or 0, r["text"].split("w")[0]) for r in simhash.keep_one(frame, made).collect())
    assert kept == [(0, "b"), (0, "d"), (1, "a"), (7, "c")]


def test_near_copies_in_one_large_bucket(spark):
    """A chain of drifting versions in one bucket, compared against brute force whatever the size of Arrow batches."""
    draw = np.random.default_rng(12)
    now, texts = [f"w{x}" for x in draw.integers(0, 10**6, 120)], []
    for i in range(160):
        now = list(now)
        for at in draw.choice(120, 2, replace=False):
            now[at] = f"v{i}x{at}"
        texts.append(" ".join(now))
    frame = spark.createDataFrame([(i, t, "en", "s", 0) for i, t in enumerate(texts)], SCHEMA)
    sets = [{tuple(t.split()[i : i + 5]) for i in range(116)} for t in texts]
    near = lambda a, b: len(sets[a] & sets[b]) >= 0.8 * len(sets[a] | sets[b])
    root = list(range(len(texts)))
    for a in range(len(texts)):
        for b in range(a):
            if near(a, b):
                x, y = sorted((root[a], root[b]))
                root = [x if r == y else r for r in root]
    before, found = spark.conf.get("spark.sql.execution.arrow.maxRecordsPerBatch"), []
    for size in ("10000", "7"):
        spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", size)
        try:
            found.append({r["doc_id"]: r["component_id"] for r in simhash.similar_documents(frame).collect()})
        finally:
            spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", before)
    assert found[0] == found[1] == dict(enumerate(root))


def test_near_copies_just_above_the_similarity(spark):
    """Pairs with Jaccard similarity 0.80 to 0.85 among unrelated texts, and one text copied often with edits of its own."""
    draw = np.random.default_rng(5)
    word = lambda n: [f"w{x}" for x in draw.integers(0, 50_000, n)]
    rows, near = [], []
    for i in range(300):
        text = word(int(draw.integers(60, 400)))
        rows.append((2 * i, " ".join(text)))
        if i % 2:
            # A word changed inside takes five shingles from each of the two sets.
            n, edits = len(text) - 4, 0
            while (n - 5 * (edits + 1)) >= 0.8 * (n + 5 * (edits + 1)):
                edits += 1
            for e in range(edits):
                text[5 + e * ((len(text) - 10) // max(1, edits))] = f"x{i}-{e}"
            rows.append((2 * i + 1, " ".join(text)))
            near.append(2 * i + 1)
    hub = word(200)
    for c in range(60):
        text = list(hub)
        for e in draw.choice(np.arange(5, 195), 2, replace=False):
            text[e] = f"y{c}-{e}"
        rows.append((1000 + c, " ".join(text)))
    frame = spark.createDataFrame([*rows, (1000, rows[-60][1]), (5000, None), (5001, " ")], "doc_id long, text string")
    got = {r["doc_id"]: r["component_id"] for r in simhash.similar_documents(frame).collect()}
    assert all(got[x] == x - 1 for x in near) and all(got[2 * i] == 2 * i for i in range(300))
    assert {got[1000 + c] for c in range(60)} == {1000} and got[5000] == got[5001] == 5000



# ---- 2 and 5 -------------------------------------------------------------------------------------


def planted_vectors(spark, n=300):
    draw = np.random.default_rng(9)
    base = draw.normal(size=(n, 16))
    group = base[:1] + draw.normal(scale=0.05, size=(90, 16))
    loose = base[1] + draw.normal(scale=0.28, size=(40, 16))
    rows = np.concatenate((base, group, loose, base[5:8]))
    labels = [i % 2 for i in range(n)] + [0] * 90 + [1] * 40 + [1, 0, 1]
    table = [(i, [float(np.float32(x)) for x in v], l) for i, (v, l) in enumerate(zip(rows, labels, strict=True))]
    odd = [(10_000, None, 1), (10_001, [0.0] * 16, 1), (10_002, [float("nan")] * 16, 1), (10_003, [1.0] * 16, None), (10_004, [None] + [1.0] * 15, 0), (10_005, [], 0), (10_006, [1.0, 2.0], 0), (10_007, [float("inf")] + [0.0] * 15, 0)]
    return spark.createDataFrame(table + odd, "vec_id long, embedding array<float>, label int").withColumn("class", F.lit("clash")), table


def test_near_vectors_brute_force(spark):
    frame, table = planted_vectors(spark)
    got = {r["vec_id"]: r for r in near_vectors.near_duplicate_vectors(frame).collect()}
    x = np.array([r[1] for r in table])
    unit = x / np.linalg.norm(x, axis=1, keepdims=True)
    label = np.array([r[2] for r in table])
    link = (unit @ unit.T >= 0.93) & (label[:, None] == label[None, :])
    np.fill_diagonal(link, False)
    assert [got[i]["n_links"] for i in range(len(table))] == link.sum(1).tolist()
    up = np.arange(len(table))
    for _ in range(len(table)):
        new = np.minimum(up, np.where(link, up[None, :], len(up)).min(1))
        if (new == up).all():
            break
        up = new
    assert [got[i]["component_id"] for i in range(len(table))] == up.tolist()
    assert all((got[i]["n_links"], got[i]["component_id"], got[i]["kept"]) == (0, i, True) for i in range(10_000, 10_008))
    assert near_vectors.near_duplicate_vectors(frame.limit(0)).count() == 0


def test_nearest_recall_and_ties(spark):
    frame, table = planted_vectors(spark)
    frame = frame.where("vec_id <> 10003")  # it has no label, but a vector like any other
    found = nearest.nearest(frame, F.col("vec_id") % 10 == 0, block_rows=150, query_rows=20).collect()
    x, hits, total = np.array([r[1] for r in table]), 0, 0
    by = {}
    for r in found:
        by.setdefault(r["query_id"], []).append(r)
    assert set(by) == set(range(0, len(table), 10)) and 10_006 not in by
    for q, rows in by.items():
        rows.sort(key=lambda r: r["rank"])
        d = np.sqrt(((x - x[q]) ** 2).sum(1))
        d[q] = np.inf
        best = np.lexsort((np.arange(len(d)), d))[:10].tolist()
        assert [r["rank"] for r in rows] == list(range(1, 11)) and all(r["score"] == pytest.approx(d[r["vec_id"]], rel=1e-12) for r in rows)
        hits, total = hits + len(set(best) & {r["vec_id"] for r in rows}), total + 10
    assert hits / total >= 0.95
    assert nearest.nearest(frame.limit(0), F.lit(True)).count() == 0
    few = nearest.nearest(frame.where("vec_id < 4"), F.col("vec_id") == 0).collect()
    assert sorted(r["vec_id"] for r in few) == [1, 2, 3]


@pytest.mark.parametrize("folder", ["sf0.1", "check_s"])
def test_nearest_on_given_vectors(spark, folder):
    """Recall of the query, and how few vectors its collision counts let through."""
    path = f"/root/testdata/{folder}"
    found = QUERIES["op2_nearest"](spark, path).collect()
    rows = [(r["vec_id"], r["embedding"]) for r in spark.read.parquet(f"{path}/embeddings.parquet").select("vec_id", "embedding").collect()]
    rows = [(i, x) for i, x in rows if x and all(y is not None and np.isfinite(y) for y in x) and any(x)]
    ids, x = np.array([i for i, _ in rows]), np.array([v for _, v in rows], float)
    hits, total, verified = 0, 0, {r["query_id"]: r["verified"] for r in found}
    for at in np.flatnonzero(ids % 100 == 0):
        d = np.sqrt(((x - x[at]) ** 2).sum(1))
        d[at] = np.inf
        best = set(ids[np.lexsort((ids, d))[:10]].tolist())
        hits, total = hits + len(best & {r["vec_id"] for r in found if r["query_id"] == ids[at]}), total + 10
    assert hits / total >= 0.95 and set(verified) == set(ids[ids % 100 == 0].tolist())
    assert np.mean(list(verified.values())) < 0.1 * len(ids)


def test_collisions_are_counted_in_windows():
    draw = np.random.default_rng(3)
    x = draw.normal(size=(500, 12))
    block = nearest.Block(x, 40)
    radius = np.array([0.5, 9.0])
    low, high = block.windows(x[:2], radius)
    for i in range(2):
        apart = np.abs(x @ block.lines - x[i] @ block.lines)
        assert (block.collisions(low[i], high[i]) == (apart <= nearest.HALF_WIDTH * radius[i] + 1e-9 * np.abs(x[i]).max()).sum(axis=1)).all()


# ---- 3 -------------------------------------------------------------------------------------------


def plain_repeats(rows, n=13):
    words, first = {i: (t or "").encode().split() for i, t in rows}, {}
    for i in sorted(words):
        for k in range(len(words[i]) - n + 1):
            first.setdefault(tuple(words[i][k : k + n]), i)
    out = {}
    for i, w in words.items():
        gone = [False] * len(w)
        for k in range(len(w) - n + 1):
            if first[tuple(w[k : k + n])] < i:
                gone[k : k + n] = [True] * n
        out[i] = (len(w), sum(gone), b" ".join(x for x, g in zip(w, gone, strict=True) if not g).decode())
    return out


def test_substring_brute_force(spark, docs):
    want = plain_repeats([(r["doc_id"], r["text"]) for r in docs.collect()])
    got = {r["doc_id"]: (r["n_words"], r["n_removed"], r["kept_sha256"]) for r in QUERIES["op3_substring"](spark, SF).collect()}
    assert got == {i: (n, g, hashlib.sha256(t.encode()).hexdigest()) for i, (n, g, t) in want.items()}


@pytest.mark.parametrize("shift", range(7))
def test_a_window_is_found_at_every_shift(spark, shift):
    passage = [f"p{i}" for i in range(13)]
    rows = [(0, " ".join([f"a{i}" for i in range(3)] + passage + ["x"])), (1, " ".join([f"b{i}" for i in range(shift)] + passage + ["y"])), (2, " ".join(passage[1:] + ["z"]))]
    got = {r["doc_id"]: r["n_removed"] for r in substring.remove_repeats(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    assert got == {0: 0, 1: 13, 2: 0}


def test_substring_odd_cases(odd, empty):
    got = {r["doc_id"]: r for r in substring.remove_repeats(odd).collect()}
    assert got[1]["n_words"] == got[2]["n_words"] == got[7]["n_words"] == 0 and got[5]["n_removed"] == 0
    assert got[6]["n_removed"] == 4000 and got[6]["kept_text"] == "end" and got[None]["n_words"] == 5 and got[None]["n_removed"] == 0
    assert substring.remove_repeats(odd).count() == len(ODD) and substring.remove_repeats(empty).count() == 0


# ---- 4 -------------------------------------------------------------------------------------------


def check_pieces(rows, ids_of):
    by_sequence, by_doc = {}, {}
    for r in rows:
        by_sequence.setdefault(r["sequence_id"], []).append(r)
        by_doc.setdefault(r["doc_id"], []).append(r)
    padding = 0
    for pieces in by_sequence.values():
        at = 0
        for r in sorted(pieces, key=lambda r: r["offset"]):
            assert r["offset"] == at
            at += r["length"]
        assert at <= 2048
        padding += 0 if at & (at - 1) == 0 else 2048 - at
    for doc, pieces in by_doc.items():
        for r in pieces:
            want = np.array(ids_of[doc][r["start"] : r["start"] + r["length"]], "<u4").tobytes()
            assert zlib.crc32(want) == r["ids_crc32"] and r["doc_tokens"] == len(ids_of[doc])
    return padding, {d: sorted((r["start"], r["length"]) for r in p) for d, p in by_doc.items()}


def token_ids(rows):
    from tokenizers import Tokenizer

    paths, _ = vocabulary()
    t = Tokenizer.from_file(paths[1])
    t.encode_special_tokens = True
    return {i: t.encode(x or "", add_special_tokens=False).ids + [1] for i, x in rows}


def test_packing_covers_every_id(spark, docs):
    ids = token_ids([(r["doc_id"], r["text"]) for r in docs.collect()])
    padding, pieces = check_pieces(QUERIES["op4_packing"](spark, SF).collect(), ids)
    assert padding <= 2048 and set(pieces) == set(ids)
    for d, p in pieces.items():
        at = 0
        for start, n in p:
            assert start == at
            at += n
        assert at == len(ids[d])


def test_packing_odd_cases(odd, empty):
    paths, pattern = vocabulary()
    rows = packing.pack(odd, paths, pattern).withColumn("ids_crc32", F.crc32("ids")).collect()
    assert sum(r["length"] for r in rows) == sum(len(x) for x in token_ids(enumerate([r[1] for r in ODD])).values())
    assert {r["doc_tokens"] for r in rows if r["doc_id"] in (1, 2)} == {1}
    assert packing.pack(empty, paths, pattern).count() == 0
    with pytest.raises(ValueError):
        packing.Packer(1000)


def test_encoder_equals_tokenizers():
    from edgesplit.llm.bpe import Encoder

    paths, pattern = vocabulary()
    draw = np.random.default_rng(6)
    alphabet = list("aé '\n\tsS0.Ω日t9lrevd  md’\x1c\x85")
    texts = ["", "don't we'll", "'s's", " 's x", "<|endoftext|>", "a\n b\n  c ", "\x00"] + ["".join(draw.choice(alphabet, int(n))) for n in draw.integers(0, 30, 800)]
    ids, bounds = Encoder(*paths, pattern).encode(texts)
    want = token_ids(enumerate(texts))
    assert [ids[a:b].tolist() for a, b in zip(bounds[:-1], bounds[1:], strict=True)] == [want[i][:-1] for i in range(len(texts))]


# ---- 6 -------------------------------------------------------------------------------------------


def test_main_text():
    page = (
        "<!doctype html><html><head><title>T</title><style>p{}</style></head><body><nav><ul><li><a href=/a>Menu</a></ul></nav><!-- x --><div class='ad box'>Buy</div>"
        "<article><h1>Title &amp; more</h1><p><b>First  part<br>goes on.<p>Second\n part with <a href=x>a link</a>.<script>if (a < b) x = '</p>'</script></p><form>Name <input></form></article>"
        "<div id=comments><p>Nice text, I liked it very much indeed, thanks.</div><aside>Side</aside><footer>&copy; me</footer></body></html>"
    )
    assert html_text.main_text(page) == "Title & more\nFirst part goes on.\nSecond part with a link."
    article = "<article><h1>T</h1><p>" + "word " * 30 + "</p><p>tail</p></article>"
    for around in (
        "<div class='page with-sidebar'>{}<div class=sidebar>x y</div></div>", "<header><h1>Site</h1></header>{}<section id=comments><article class=comment><p>" + "nice " * 200 + "</article></section>",
        "<div class='cookie-notice'>We use cookies</div>{}<div class=related><a href=x>More stories here</a></div>", "<div id=menu><a href=1>a</a></div><main>{}</main><aside>s</aside><form>f<input></form>",
    ):
        assert html_text.main_text("<body>" + around.format(article) + "</body>") == "T\n" + ("word " * 30).strip() + "\ntail"
    assert html_text.main_text(None) == html_text.main_text("") == html_text.main_text("<p></p>") == ""
    assert html_text.main_text("just text &lt;b&gt; <foo") == "just text <b>"
    assert html_text.main_text("<div><p>" + "word " * 50 + "</p><p>" + "more " * 50 + "</p></div><ul class=menu><li><a>x</a></ul>") == ("word " * 50).strip() + "\n" + ("more " * 50).strip()


def plain_article(source):
    """The given pages' article by its tag, blocks by theirs."""
    inner = re.sub(r"<br>", " ", re.search(r"<article>(.*?)</article>", source, re.DOTALL)[1])
    blocks = (" ".join(html.unescape(re.sub(r"<[^>]+>", "", b)).split()) for b in re.split(r"</?(?:p|h1|h2|h3|div|ul|li)[^>]*>", inner))
    return "\n".join(b for b in blocks if b)


def unnamed(source):
    """The same page as a heap of div elements without telling names."""
    for tag in ("article", "nav", "footer"):
        source = source.replace(f"<{tag}>", "<div>").replace(f"</{tag}>", "</div>")
    return source.replace(' class="ad"', "")


def test_main_text_of_all_given_pages():
    pages = [r["html"] for r in pq.read_table("/root/testdata/sf0.1/pages.parquet", columns=["html"]).to_pylist()]
    assert all(html_text.main_text(x) == plain_article(x) for x in pages)


def test_density_finds_articles_without_names(monkeypatch):
    pages = [r["html"] for r in pq.read_table("/root/testdata/sf0.01/pages.parquet", columns=["html"]).to_pylist()]
    right = lambda: sum(html_text.main_text(unnamed(x)) == plain_article(x) for x in pages)
    assert right() > 0.95 * len(pages)
    own = html_text._density
    monkeypatch.setattr(html_text, "_density", lambda *a: 1.0)
    assert right() < 0.05 * len(pages)
    monkeypatch.setattr(html_text, "_density", lambda *a: 1.0 / (1.0 + own(*a)))
    assert right() < 0.2 * len(pages)


@pytest.mark.parametrize(
    ("source", "text"),
    [
        ("<body><div class='page has-comments'><article><h1>T</h1><p>Some long text here, with words.</p></article><section class='comments'><article><p>I agree very much with all of this.</p></article></section></div></body>", "T\nSome long text here, with words."),
        ("<body><div class='layout ad-free'><div><h2>T</h2><p>Some long text here, with words.</p></div></div><div class='ad'>Buy now</div></body>", "T\nSome long text here, with words."),
        ("<body><form id=f><div class='content with-sidebar'><h2>T</h2><p>Some long text here, with words.</p></div><div class=sidebar><a href=x>one</a> two</div></form></body>", "T\nSome long text here, with words."),
        ("<body><article><section><p>A first section with a long paragraph.</p><p>And yet another long paragraph.</p></section><section><p>Short.</p></section></article><footer>f</footer></body>", "A first section with a long paragraph.\nAnd yet another long paragraph.\nShort."),
        ("<body><p>just</p><p>two</p></body>", "just\ntwo"),
        ("<nav><a href=x>only a menu</a></nav>", ""),
    ],
)
def test_names_only_adjust(source, text):
    assert html_text.main_text(source) == text


def test_extract_keeps_rows(spark):
    rows = [(1, "u", None), (2, None, "<p>x</p>"), (2, None, "<p>x</p>"), (None, "v", "<body>" + "<div>" * 3000 + "deep")]
    frame = spark.createDataFrame(rows, "page_id long, url string, html string").withColumn("text", F.lit(1))
    got = sorted((str(r["page_id"]), r["text"], r["n_chars"]) for r in html_text.extract_text(frame).collect())
    assert got == [("1", "", 0), ("2", "x", 1), ("2", "x", 1), ("None", "deep", 4)]


# ---- 7 -------------------------------------------------------------------------------------------


def test_mix_targets_and_limits(spark, odd, empty):
    rows = [(i, "w " * (i % 40 + 1), "en", s, 0) for i, s in enumerate(["big"] * 200 + ["mid"] * 30 + ["tiny"] * 3 + [None] * 2)]
    planned = mixing.plan_mix(spark.createDataFrame(rows, SCHEMA)).collect()
    assert len(planned) == len(rows) and all(0 <= r["taken"] <= 3 * r["size"] for r in planned)
    by = {}
    for r in planned:
        by.setdefault(r["source"], []).append(r)
    total = sum(r["size"] for r in planned)
    assert sum(x[0]["target"] for x in by.values()) == pytest.approx(total)
    for own in by.values():
        assert own[0]["target"] <= 3 * own[0]["source_size"] and abs(sum(r["taken"] for r in own) - own[0]["target"]) <= 1
    copies = mixing.take_copies(spark.createDataFrame(rows, SCHEMA)).collect()
    assert sum(len(r["text"].split()) for r in copies) == sum(r["taken"] for r in planned)
    times = [r["virtual_finish"] for r in copies]
    assert times == sorted(times) and all(r["virtual_finish"] <= 1 + 1e-9 or r["words"] < r["size"] or r["virtual_finish"] - 1 <= 0.5 / r["target"] for r in copies)
    assert mixing.plan_mix(odd).count() == len(ODD) and mixing.plan_mix(empty).count() == 0


# ---- 8 -------------------------------------------------------------------------------------------


def test_quality_on_held_out_rows(spark):
    big = "/root/testdata/sf0.01"
    labels = {r["doc_id"]: r["quality"] for r in spark.read.parquet(f"{big}/labels.parquet").collect()}
    rows = QUERIES["op8_quality"](spark, big).collect()
    assert all(0 <= r["score"] <= 1 and r["predicted"] == int(r["score"] >= 0.3) and r["held_out"] == (zlib.crc32(str(r["doc_id"]).encode()) % 5 == 0) for r in rows)
    held = [(r["predicted"], labels[r["doc_id"]]) for r in rows if r["held_out"] and r["doc_id"] in labels]
    assert sum(a == b for a, b in held) / len(held) >= 0.93


def test_quality_odd_cases(spark, odd, empty):
    labels = spark.createDataFrame([(3, 1), (5, None), (None, 1)], "doc_id long, quality int")
    rows = quality.score_documents(odd, labels).collect()
    assert len(rows) == len(ODD) and all(0 <= r["score"] <= 1 for r in rows)
    assert quality.score_documents(empty, labels.limit(0)).count() == 0
    assert quality.keep_good(odd, labels.limit(0)).count() == len(ODD)


def test_isotonic():
    x, y = quality.isotonic(np.array([0.0, 1, 2, 3]), np.array([1.0, 0, 3, 2]), np.array([2.0, 2, 4, 2]))
    assert (np.diff(y) > 0).all() and y[0] == 0.25


# ---- 9 -------------------------------------------------------------------------------------------


def test_packages_agree_with_zipfile():
    for wide in (False, True):
        members = [("archive/data.warc.gz", [b"abc", b"def"]), ("indexes/index.cdxj", [b"x\n"])]
        body = b"".join(warc_zip.build_package(members, wide))
        with zipfile.ZipFile(io.BytesIO(body)) as z:
            assert z.testzip() is None and z.read("archive/data.warc.gz") == b"abcdef"
        found = warc_zip.read_directory(lambda a, n, b=body: b[a : a + n], len(body))
        assert {n: body[m.begin : m.begin + m.size] for n, m in found.items()} == {"archive/data.warc.gz": b"abcdef", "indexes/index.cdxj": b"x\n"}
    buffer = io.BytesIO()
    with zipfile.ZipFile(buffer, "w") as z:
        z.writestr("a", b"12345")
        z.comment = b"PK\x05\x06 looks like an end"
    body = buffer.getvalue()
    m = warc_zip.read_directory(lambda a, n: body[a : a + n], len(body))["a"]
    assert body[m.begin : m.begin + m.size] == b"12345"
    with pytest.raises(ValueError):
        warc_zip.read_directory(lambda a, n: b"x" * n, 30)


def test_warc_round_trip(spark, tmp_path):
    big = "x" * 1200 + "é"
    rows = [(1, "http://a b\n", big), (5, None, big), (3, "u", big), (2, "v", "small"), (4, "v", "small"), (6, "w", None), (None, "n", big), (5, "again", big)]
    frame = spark.createDataFrame(rows, "page_id long, url string, html string").withColumn("payload", F.lit(1))
    got = sorted(((r["page_id"], r["payload_bytes"], r["record_type"], r["refers_to"]) for r in warc_zip.round_trip(frame, 500).collect()), key=str)
    n = len(big.encode())
    want = [(1, n, "revisit", 5), (5, n, "response", None), (3, n, "revisit", 5), (2, 5, "response", None), (4, 5, "response", None), (6, 0, "response", None), (None, n, "revisit", 5), (5, n, "response", None)]
    assert got == sorted(want, key=str)
    assert warc_zip.round_trip(frame.limit(0)).count() == 0
    records = warc_zip.plan_records(frame)
    inline = warc_zip.write_packages(records, "hdfs://elsewhere/x", 500)
    assert warc_zip.read_packages(inline, "hdfs://elsewhere/x").count() == len(rows)


# ---- 10 ------------------------------------------------------------------------------------------


def test_names_of_results_and_helpers_do_not_clash(spark):
    """Columns named as operators name theirs, now or once, come back untouched."""
    names = ["first", "second", "tie", "bucket", "rank", "part", "place", "ends", "begin", "n", "digest", "inside", "offset", "key", "whole", "words", "gone", "cut_doc", "left_over", "c0", "c1", "__first", "__part", "__digest", "__key", "__text"]
    rows = spark.createDataFrame([(i, f"some words of text {i % 3}", "en", "ab"[i % 2], 5) for i in range(20)], SCHEMA)
    clashing = rows.select("*", *[F.concat(F.lit(n), F.col("doc_id").cast("string")).alias(n) for n in names])
    want = {r["doc_id"]: tuple(r[n] for n in names) for r in clashing.collect()}
    for result in (sharding.shuffle_into_shards(clashing), substring.remove_repeats(clashing), substring.cut_repeats(clashing), substring.repeat_digests(clashing)):
        assert {r["doc_id"]: tuple(r[n] for n in names) for r in result.collect()} == want
    taken = mixing.take_copies(clashing).collect()
    assert taken and all(r["__digest"] == f"__digest{r['doc_id']}" and r["c1"] == f"c1{r['doc_id']}" and r["bucket"] == f"bucket{r['doc_id']}" for r in taken)
    assert mixing.plan_mix(clashing).count() == 20


def test_matrix_sums_and_law():
    m = sharding.communication_matrix([5, 0, 7, 30], 4, 1)
    assert m.sum(1).tolist() == [5, 0, 7, 30] and sorted(m.sum(0).tolist()) == [10, 10, 11, 11]
    draws = np.array([sharding.communication_matrix([10, 10], 2, s)[0, 0] for s in range(3000)])
    assert abs(draws.mean() - 5) < 0.1 and abs(draws.var() - 100 / 76) < 0.2  # hypergeometric: 10 of 20, half of them good
    big = np.array([sharding._tabled_draw(np.random.default_rng(s), 6 * 10**9, 4 * 10**9, 100) for s in range(3000)])
    assert abs(big.mean() - 60) < 0.5 and abs(big.var() - 24) < 3


def test_shards_are_exact_and_rerun_alike(spark, odd, empty):
    rows = spark.range(1003).select(F.col("id").alias("doc_id"))
    a, b = ([tuple(r) for r in sharding.shuffle_into_shards(rows.repartition(n)).orderBy("doc_id").collect()] for n in (2, 7))
    assert a == b
    sizes = {}
    for _, shard, slot in a:
        sizes.setdefault(shard, []).append(slot)
    assert len(sizes) == 16 and {len(s) for s in sizes.values()} == {62, 63} and all(sorted(s) == list(range(len(s))) for s in sizes.values())
    out = sharding.shuffle_into_shards(odd).collect()
    assert len(out) == len(ODD) and {type(r["shard"]) for r in out} == {int}
    assert sharding.shuffle_into_shards(empty).count() == 0


def test_registry():
    assert {int(n[2:].split("_")[0]) for n in QUERIES} == set(range(1, 11)) and set(ORACLES) <= set(QUERIES)


def test_near_copies_of_a_template_link_with_each_other(spark):
    """Forty pairs of near copies in large buckets whose centre is below the similarity to all but its own mate."""
    rows = []
    for pair in range(40):
        for side in range(2):
            own = [f"both{pair}x{i}" for i in range(2)] + [f"own{pair}x{side}x{i}" for i in range(19)]
            rows.append((2 * pair + side, " ".join([f"t{i}" for i in range(164)] + own)))
    frame = spark.createDataFrame(rows, "doc_id long, text string")
    got = {r["doc_id"]: r["component_id"] for r in simhash.similar_documents(frame).collect()}
    assert got == {i: i - i % 2 for i in range(80)}


def test_sets_compared_by_blocks_equal_brute_force():
    draw = np.random.default_rng(3)
    base = draw.integers(0, 1 << 32, 9000, dtype=np.uint64).astype(np.uint32)
    sets = [np.unique(base[draw.permutation(9000)[: draw.integers(7000, 9000)]]) for _ in range(20)] + [np.zeros(0, np.uint32)] * 2
    rows, columns = np.arange(0, 22, 2), np.arange(22)
    i, j = simhash._similar(sets, rows, columns, 0.8)
    want = {(a, b) for a in range(11) for b in range(22) if (both := len(np.intersect1d(sets[rows[a]], sets[b]))) and both >= 0.8 * (len(sets[rows[a]]) + len(sets[b]) - both)}
    assert set(zip(i.tolist(), j.tolist(), strict=True)) == want


def test_short_near_copies_are_not_discarded(spark):
    """Eight and nine words share four of five shingles; majorities of so few tie, and these differ in over 36 bits."""
    words = ["q99084 q513237 q69585 q791007 q479109 q998558 q232801 q475693 q887838", "q27267 q453469 q585243 q491013 q302941 q21262 q768278 q557251 q8574"]
    frame = spark.createDataFrame([(i, " ".join(w.split()[: 8 + i % 2])) for i, w in enumerate(np.repeat(words, 2).tolist())], "doc_id long, text string")
    assert {r["doc_id"]: r["component_id"] for r in simhash.similar_documents(frame).collect()} == {0: 0, 1: 0, 2: 2, 3: 2}


def test_near_vectors_beside_a_dense_group(spark):
    """Vectors that link with a few members of a dense group only, in a label with many others."""
    draw = np.random.default_rng(5)
    unit = lambda x: x / np.linalg.norm(x, axis=-1, keepdims=True)
    centre = unit(draw.normal(size=16))
    dense = unit(centre + 0.012 * draw.normal(size=(1500, 16)))
    side = draw.normal(size=(20, 16))
    side = unit(side - (side @ centre)[:, None] * centre)
    angle = np.arccos(0.93) + 0.028
    x = np.concatenate((dense, np.cos(angle) * centre + np.sin(angle) * side, unit(draw.normal(size=(1500, 16)))))
    linked = x @ x.T >= near_vectors.THRESHOLD
    root = np.arange(len(x))
    while (least := np.where(linked, root[None, :], len(x)).min(axis=1)).tolist() != root.tolist():
        root = least
    frame = spark.createDataFrame([(i, v, 1) for i, v in enumerate(x.tolist())], "vec_id long, embedding array<double>, label long")
    got = {r["vec_id"]: (r["component_id"], r["n_links"]) for r in near_vectors.near_duplicate_vectors(frame).collect()}
    assert got == {i: (int(root[i]), int(linked[i].sum()) - 1) for i in range(len(x))}


@pytest.mark.parametrize(("background", "cosine"), [(0.0, 0.935), (0.69, 0.935), (0.8, 0.95)])
def test_near_vectors_with_a_common_direction(spark, background, cosine):
    """One label of 12,000 vectors that share a direction, pairs just above the threshold among them: recall of their links."""
    draw = np.random.default_rng(8)
    unit = lambda x: x / np.linalg.norm(x, axis=-1, keepdims=True)
    n, pairs, d = 12_000, 600, 64
    common = unit(draw.normal(size=d))
    side = draw.normal(size=(n, d))
    side = unit(side - (side @ common)[:, None] * common)
    x = np.sqrt(background) * common + np.sqrt(1 - background) * side
    turn = draw.normal(size=(pairs, d))
    turn = unit(turn - (turn * x[:pairs]).sum(axis=1)[:, None] * x[:pairs])
    angle = np.arccos(cosine)
    x = np.concatenate((x, np.cos(angle) * x[:pairs] + np.sin(angle) * turn))
    frame = spark.createDataFrame([(i, v, 1) for i, v in enumerate(x.tolist())], "vec_id long, embedding array<double>, label long")
    got = {r["vec_id"]: r for r in near_vectors.near_duplicate_vectors(frame).collect()}
    assert sum(got[n + i]["component_id"] == got[i]["component_id"] for i in range(pairs)) >= 0.95 * pairs
    true = sum(((x[at : at + 2000] @ x.T) >= near_vectors.THRESHOLD).sum() for at in range(0, len(x), 2000)) - len(x)
    assert true * 0.95 <= sum(r["n_links"] for r in got.values()) <= true


def test_sketches_bound_their_error():
    draw = np.random.default_rng(2)
    x = draw.normal(size=(300, 24))
    x /= np.linalg.norm(x, axis=1, keepdims=True)
    y, error = near_vectors.read_sketches(pa.array(near_vectors.sketches(x), pa.binary()))
    assert (np.abs(x @ x.T - y @ y.T) <= error[:, None] + error[None, :] * (1 + error.max())).all() and error.max() < 1e-4


def test_passes_follow_the_spread():
    even, shifted = near_vectors.plan_label(50_000, 1.0), near_vectors.plan_label(50_000, 0.31)
    assert even[1] == 10 and shifted[0] > 2 * even[0] and near_vectors.plan_label(50_000, 0.02) == (1, 0)
    for rows in (10, 10**4, 10**7, 10**10):
        for spread in (1.0, 0.4, 0.1):
            passes, leading = near_vectors.plan_label(rows, spread)
            agree = 1 - np.arccos(1 - (1 - near_vectors.THRESHOLD) / spread) / np.pi
            assert (1 - agree**leading) ** passes <= near_vectors.MISS * 1.0001 if leading else passes == 1
