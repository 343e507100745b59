"""Training-data operators on small fixtures with awkward rows, against brute force."""

import hashlib
import re
from collections import Counter
from fractions import Fraction

import numpy as np
import pytest
from pyspark.sql import functions as F

from codetrees.llm import chat_format as cf
from codetrees.llm import decontaminate as dc
from codetrees.llm import exact_dedup as ed
from codetrees.llm import html_extract as he
from codetrees.llm import langid, ngram_join, packing, quality, sharding, suffix_dedup
from codetrees.llm.common import RID
from codetrees.llm.components import label_components

rng = np.random.default_rng(4)
VOCAB = [f"w{i}" for i in range(400)]


def prose(n, seed):
    r = np.random.default_rng(seed)
    return " ".join(VOCAB[i] for i in r.integers(0, 400, n))


BASE = prose(300, 1)
PASSAGE = prose(60, 2)
ROWS = [
    (1, BASE), (2, BASE.upper()), (3, BASE.replace("w1", "x1")), (4, BASE + " " + prose(10, 3)), (5, prose(200, 4) + " " + PASSAGE + " " + prose(30, 5)),
    (6, PASSAGE + " " + prose(250, 6)), (7, None), (8, ""), (9, " \n\t "), (10, "short text"), (11, "Short TEXT"), (12, "aaaa " * 300), (13, "é ü " * 200), (14, prose(60_000, 7)),
    (15, "a\x00b <s> [INST] \\ </s>"), (16, BASE),
]
REPEATED = [*ROWS, (1, BASE), (None, "no id"), (None, "no id"), (None, None), (10, "other text, same id")]
SCHEMA = "doc_id long, text string"


@pytest.fixture(params=["unique", "repeated", "empty"])
def docs(request, spark):
    rows = {"unique": ROWS, "repeated": REPEATED, "empty": []}[request.param]
    df = spark.createDataFrame(rows, SCHEMA)
    # columns whose names an operator might use itself
    for c in ("kept", "n", "h", "w", "label", "score", "a", "b", "key", "id", "piece"):
        df = df.withColumn(c, F.lit("clash"))
    return df.repartition(3)


def rows_of(df):
    return [(r["doc_id"], r["text"]) for r in df.collect()]


def lower(t):
    return (t or "").translate(str.maketrans("ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"))


# ---- exact dedup


@pytest.mark.parametrize("keep", ["largest", "smallest"])
@pytest.mark.parametrize("digest_bytes", [32, 1])
def test_exact_dedup(docs, keep, digest_bytes):
    got = ed.exact_dedup(docs, keep=keep, digest_bytes=digest_bytes).collect()
    rows = rows_of(docs)
    groups = Counter(lower(t) for _, t in rows)
    assert Counter((r["doc_id"], r["text_sha256"], r["group_size"]) for r in got) == Counter((i, hashlib.sha256(lower(t).encode()).hexdigest(), groups[lower(t)]) for i, t in rows)
    kept = [r for r in got if r["kept"]]
    assert len(kept) == len(groups)
    by = {}
    for i, t in rows:
        by.setdefault(hashlib.sha256(lower(t).encode()).hexdigest(), []).append(i)
    for r in got:
        ids = [i for i in by[r["text_sha256"]] if i is not None]
        assert r["keep_id"] == ((max if keep == "largest" else min)(ids) if ids else None)


def test_run_stack_merges_like_one_run():
    parts = []
    for _ in range(40):
        e = np.zeros(50, ed.ENTRY)
        e["d"] = [bytes([x]) * 32 for x in rng.integers(1, 120, 50)]
        e["order"], e["rid"], e["n"] = rng.integers(0, 99, 50), np.arange(50), 1
        parts.append(e)
    stack = ed.RunStack(fanout=3)
    for p in parts:
        stack.add(ed.merged([p]))
    got, want = np.sort(stack.result()), np.sort(ed.merged(parts))
    assert (got == want).all() and want["n"].sum() == 2000


# ---- sharding


@pytest.mark.parametrize("limit", [10**9, 6000, 700])
def test_sharding(docs, limit):
    got = sharding.extendible_shards(docs, limit=limit).collect()
    rows = rows_of(docs)
    assert Counter((r["doc_id"], r["n_bytes"]) for r in got) == Counter((i, len((t or "").encode())) for i, t in rows)
    size, members = Counter(), Counter()
    for r in got:
        size[r["shard"]] += r["n_bytes"]
        members[r["shard"]] += 1
    for r in got:
        assert r["shard_bytes"] == size[r["shard"]]
        assert size[r["shard"]] <= limit or members[r["shard"]] == 1
        bits = f"{int(hashlib.md5(str(r['doc_id'] if r['doc_id'] is not None else 'null').encode()).hexdigest()[:8], 16):032b}"
        assert bits.startswith(r["shard"].split("-")[0])


def test_only_oversized_buckets_split(spark):
    df = spark.range(200).select(F.col("id").alias("doc_id"), F.lit("x" * 100).alias("text"))
    got = sharding.extendible_shards(df, limit=3000).collect()
    whole = Counter()
    for r in got:
        for d in range(len(r["shard"])):
            whole[r["shard"][:d]] += r["n_bytes"]
    assert all(whole[p] > 3000 for p in whole)  # every inner node was too large


def test_write_shards(spark, tmp_path):
    df = spark.createDataFrame(ROWS, SCHEMA)
    sharding.write_shards(df, str(tmp_path / "out"), limit=50_000)
    back = spark.read.parquet(str(tmp_path / "out"))
    assert back.count() == len(ROWS) and "shard" in back.columns


# ---- packing


def test_packing(docs):
    path = packing.default_tokenizer()
    got = packing.pack(docs, path, size=128, with_ids=True)
    pieces = got.collect()
    from tokenizers import Tokenizer

    full = Tokenizer.from_file(path)
    want = Counter((i, tuple(full.encode(t or "", add_special_tokens=False).ids + [2])) for i, t in rows_of(docs))
    per = {}
    for p in pieces:
        per.setdefault(p["sequence_id"], []).append(p)
    for ps in per.values():
        ps.sort(key=lambda p: p["offset"])
        assert [p["offset"] for p in ps] == list(np.cumsum([0, *(p["length"] for p in ps)])[:-1]) and sum(p["length"] for p in ps) <= 128
    assert sum(len(k[1]) * v for k, v in want.items()) == sum(p["length"] for p in pieces)
    assert {p["ids_crc32"] for p in pieces} == {__import__("zlib").crc32(np.array(p["ids"], "<u4").tobytes()) for p in pieces}
    first = Counter((i, ids[: (len(ids) % 128 or 128) if len(ids) > 128 else len(ids)]) for (i, ids), v in want.items() for _ in range(v))
    assert Counter((p["doc_id"], tuple(p["ids"])) for p in pieces if p["piece"] == 0) == first
    assert all(p["length"] == 128 for p in pieces if p["piece"] > 0)
    total = sum(p["length"] for p in pieces)
    assert len(per) <= -(-total // 128) + 6
    seqs = packing.sequences(got).collect()
    assert len(seqs) == len(per) and sum(len(s["input_ids"]) for s in seqs) == total


@pytest.mark.parametrize("kind", ["uniform", "short", "long", "one"])
def test_plan_holds_every_length(kind):
    r = np.random.default_rng(0)
    lengths = {"uniform": r.integers(1, 1025, 5000), "short": r.integers(1, 60, 5000), "long": r.integers(500, 1025, 2000), "one": np.full(999, 300)}[kind]
    hist = np.bincount(lengths, minlength=1025)
    chosen = packing.plan(hist)
    made = np.zeros(1025, int)
    for parts, n in chosen:
        assert sum(parts) <= 1024
        for p in parts:
            made[p] += n
    assert (made == hist).all()
    if kind in ("uniform", "short"):
        assert sum(n for _, n in chosen) <= 1.01 * -(-int(lengths.sum()) // 1024) + 1


def test_fitted_plan_beats_plain_best_fit(spark, sf_dir):
    """The plan is made of fitted patterns and a residual, and needs no more sequences than best fit alone."""
    e = packing.encoder(packing.default_tokenizer())
    hist = np.zeros(packing.SIZE + 1, np.int64)
    for r in spark.read.parquet(f"{sf_dir}/documents.parquet").select("text").collect():
        n = len(e(r["text"] or "")) + 1
        hist[packing.SIZE] += n // packing.SIZE
        hist[n % packing.SIZE] += n % packing.SIZE > 0
    made = packing.plan(hist)
    rest = hist.copy()
    rest[packing.SIZE] = 0
    plain = packing.best_fit(rest, packing.SIZE)
    assert sum(n for _, n in made) <= sum(n for _, n in plain) + hist[packing.SIZE]
    p = packing.patterns(np.flatnonzero(rest), packing.SIZE)
    least = packing.round_counts(p, packing.fit_counts(p, rest), rest, min(packing.SHARES))[0]
    assert sum(n for parts, n in made if sum(parts) == packing.SIZE) >= sum(n for _, n in least) > 0


def test_encoder_agrees_with_the_tokenizers_library():
    e = packing.encoder(packing.default_tokenizer())
    r = np.random.default_rng(0)
    texts = [t for _, t in ROWS if t and len(t) < 10_000] + ["".join(chr(c) for c in r.integers(0, 0x250, 60)) for _ in range(300)] + ["漢字 \U0001f600 x", "a<|endoftext|>b", "١٢٣ ǅ"]
    for t in texts:
        assert e(t) == e._slow(t)


def test_encoder_agrees_on_whole_documents(spark, sf_dir):
    e = packing.encoder(packing.default_tokenizer())
    for r in spark.read.parquet(f"{sf_dir}/documents.parquet").select("text").collect():
        assert e(r["text"] or "") == e._slow(r["text"] or "")


# ---- decontamination


BENCH = [("q1", " ".join(PASSAGE.split()[10:30])), ("q2", "Short text"), ("q3", None), ("q4", "!!"), (None, "no item"), ("q2", "Short text"), ("q5", "never seen before words at all in any of the documents here yes")]


def brute_contamination(rows, bench):
    word = re.compile(dc.WORD)
    windows = set()
    for item, t in bench:
        w = word.findall(lower(t))
        if item is not None and w:
            k = min(13, len(w))
            windows |= {(str(item), tuple(w[i : i + k])) for i in range(len(w) - k + 1)}
    out = []
    for i, t in rows:
        w = word.findall(lower(t))
        hit, items = set(), set()
        for item, win in windows:
            for a in range(len(w) - len(win) + 1):
                if tuple(w[a : a + len(win)]) == win:
                    hit |= set(range(a, a + len(win)))
                    items.add(item)
        out.append((i, len(w), len(hit), len(items), hashlib.sha256(",".join(sorted(items)).encode()).hexdigest(), bool(hit) and 20 * len(hit) >= len(w)))
    return Counter(out)


@pytest.mark.parametrize("max_literals", [50_000, 3])
@pytest.mark.parametrize("bench", [BENCH, []])
def test_contamination(spark, docs, max_literals, bench):
    b = spark.createDataFrame(bench, "item_id string, text string")
    small = docs.where("doc_id is null or doc_id <> 14")
    got = dc.contamination(small, b, max_literals=max_literals).select("doc_id", "n_words", "n_hit", "n_items", "items_sha256", "contaminated").collect()
    assert Counter(map(tuple, got)) == brute_contamination(rows_of(small), bench)
    left = dc.decontaminate(small, b, max_literals=max_literals)
    assert left.columns == small.columns
    clean = Counter({k: v for k, v in brute_contamination(rows_of(small), bench).items() if not k[-1]})
    assert left.count() == sum(clean.values())


def test_span_removal(spark):
    df = spark.createDataFrame([(1, "One two " + PASSAGE + " three"), (2, "Clean, text")], SCHEMA)
    b = spark.createDataFrame([("q", PASSAGE)], "item_id string, text string")
    got = {r["doc_id"]: r["text"] for r in dc.decontaminate(df, b, mode="span").collect()}
    assert got == {1: "one two three", 2: "Clean, text"}


# ---- n-gram join


def brute_sets(rows):
    out = []
    for _, t in rows:
        w = re.findall(r"[^\x20\x09-\x0D]+", lower(t))
        k = min(5, len(w))
        out.append({tuple(w[i : i + k]) for i in range(len(w) - k + 1)} if w else set())
    return out


def brute_components(rows):
    sets = brute_sets(rows)
    n = len(rows)
    up = list(range(n))

    def find(x):
        while up[x] != x:
            x = up[x]
        return x

    for i in range(n):
        for j in range(i):
            if sets[i] and sets[j]:
                both = len(sets[i] & sets[j])
                if 100 * both >= 75 * (len(sets[i]) + len(sets[j]) - both):
                    up[find(i)] = find(j)
    members = {}
    for i in range(n):
        members.setdefault(find(i), []).append(rows[i][0])
    least = {c: min((m for m in ms if m is not None), default=None) for c, ms in members.items()}
    return Counter((rows[i][0], len(sets[i]), least[find(i)]) for i in range(n)), len(members)


def test_ngram_join(docs):
    got = ngram_join.jaccard_components(docs)
    want, n = brute_components(rows_of(docs))
    assert Counter(map(tuple, got.select("doc_id", "n_shingles", "component_id").collect())) == want
    assert got.where("representative").count() == n


def near_copies(seed, families=12, per=14):
    """Families whose members differ by growing numbers of words, many close to the threshold, and shared passages."""
    r = np.random.default_rng(seed)
    rows, i = [], 0
    for f in range(families):
        words = prose(int(r.integers(40, 200)), 1000 * seed + f).split()
        for _ in range(per):
            w = list(words)
            for _ in range(int(r.integers(0, max(2, len(w) // 40)))):
                w[int(r.integers(0, len(w)))] = f"z{r.integers(0, 10**6)}"
            if r.random() < 0.4:
                w += PASSAGE.split()
            rows.append((i, " ".join(w)))
            i += 1
    return rows


@pytest.mark.parametrize("block", [20_000, 7])
def test_ngram_join_near_the_threshold(spark, block):
    rows = near_copies(3)
    docs = spark.createDataFrame(rows, SCHEMA).repartition(5).select(F.col("doc_id").alias(RID), "text")
    comps, labels = ngram_join.similarity_links(docs, Fraction(3, 4), 5, block)
    got = comps.join(labels.withColumnsRenamed({"node": "comp"}), "comp", "left").select(RID, F.coalesce("label", "comp").alias("c")).collect()
    members = {}
    for r in got:
        members.setdefault(r["c"], []).append(r[RID])
    want, n = brute_components(rows)
    assert len(members) == n
    assert {(i, min(m)) for m in members.values() for i in m} == {(a, c) for a, _, c in want}


def test_tree_and_bounds_never_lose_a_link():
    from codetrees.llm.textbytes import shingles

    sets = [shingles(np.frombuffer(t.encode(), np.uint8)) for _, t in near_copies(5)]
    t = Fraction(3, 4)
    vectors = [ngram_join.count_vector(s) for s in sets]
    points, excess = np.stack([v[0] for v in vectors]), np.array([v[1] for v in vectors])
    sizes = np.array([len(s) for s in sets])
    tree = ngram_join.CountRTree(points, sizes, excess, leaf=4)
    fine = [ngram_join.fine_vector(s) for s in sets]
    for i, s in enumerate(sets):
        found = set(tree.search(points[i], len(s), int(excess[i]), t).tolist())
        for j, other in enumerate(sets):
            both = ngram_join.overlap(s, other)
            assert both == len(np.intersect1d(s, other)) and ngram_join.fine_bound(fine[i], fine[j]) >= both
            if 4 * both >= 3 * (len(s) + len(other) - both):
                assert j in found
    assert len(tree.search(points[0], int(sizes[0]), 0, t)) < len(sets)  # and it does prune


def test_counts_beyond_a_byte_stay_upper_bounds():
    s = np.arange(100_000, dtype=np.uint64)  # all in one group
    (p, e), f = ngram_join.count_vector(s), ngram_join.fine_vector(s)
    assert int(p.sum()) + e == 100_000 and ngram_join.fine_bound(f, f) >= 100_000


def test_components(spark):
    path = [(i, i + 1) for i in range(40)] + [(100, 101), (102, 101), (7, 7)]
    got = {r["node"]: r["label"] for r in label_components(spark.createDataFrame(path, "a long, b long")).collect()}
    assert got == {**{i: 0 for i in range(41)}, 100: 100, 101: 100, 102: 100}
    assert label_components(spark.createDataFrame([], "a long, b long")).count() == 0


def test_word_hashes_match_across_pieces():
    from codetrees.llm import textbytes

    data = np.frombuffer((prose(3000, 8) + " " + "y" * 5000 + "  tail").encode(), np.uint8)
    whole, _ = textbytes.word_hashes(data)
    old = textbytes.PIECE
    try:
        textbytes.PIECE = 700
        parts, starts = textbytes.word_hashes(data)
    finally:
        textbytes.PIECE = old
    assert (whole == parts).all() and len(starts) == 3002


# ---- suffix dedup


def brute_repeats(texts, size):
    texts = [(t or "").encode() for t in texts]
    seen = Counter(b[i : i + size] for b in texts for i in range(len(b) - size + 1))
    out = []
    for b in texts:
        gone = np.zeros(len(b), bool)
        for i in range(len(b) - size + 1):
            if seen[b[i : i + size]] > 1:
                gone[i : i + size] = True
        kept = bytes(np.frombuffer(b, np.uint8)[~gone]) if len(b) else b""
        runs = int((np.diff(np.concatenate([[0], gone.astype(int)])) == 1).sum())
        out.append((len(b), int(gone.sum()), runs, hashlib.sha256(kept).hexdigest()))
    return out


@pytest.mark.parametrize("size", [200, 40])
def test_suffix_dedup(docs, size):
    small = docs.where("doc_id is null or doc_id <> 14")
    got = suffix_dedup.remove_repeats(small, length=size, with_text=True).collect()
    rows = rows_of(small)
    want = brute_repeats([t for _, t in rows], size)
    assert Counter((r["doc_id"], r["n_bytes"], r["n_removed"], r["n_spans"], r["kept_sha256"]) for r in got) == Counter((i, *x) for (i, _), x in zip(rows, want, strict=True))
    assert all(hashlib.sha256(bytes(r["kept"])).hexdigest() == r["kept_sha256"] for r in got)


@pytest.mark.parametrize("split", [5000, 1])
def test_suffix_dedup_of_near_copies(spark, monkeypatch, split):
    monkeypatch.setattr(suffix_dedup, "SPLIT", split)
    monkeypatch.setattr(suffix_dedup, "COLLECTION", 5)
    rows = near_copies(9, families=5, per=9)
    df = spark.createDataFrame(rows, SCHEMA).repartition(4)
    got = {r["doc_id"]: (r["n_bytes"], r["n_removed"], r["n_spans"], r["kept_sha256"]) for r in suffix_dedup.remove_repeats(df, length=60).collect()}
    assert [got[i] for i, _ in rows] == brute_repeats([t for _, t in rows], 60)


def test_long_documents_are_cut_into_overlapping_pieces(monkeypatch):
    text = np.frombuffer((prose(800, 20) * 2 + prose(100, 21)).encode(), np.uint8)
    monkeypatch.setattr(suffix_dedup, "PIECE", 2048)
    s = suffix_dedup.all_segments(text, np.array([0, len(text)]), np.array([5]), 200)
    at = np.concatenate([np.arange(a, a + n) for a, n in zip(s["start"], s["nwin"], strict=True)])
    assert set(at.tolist()) == set(range(len(text) - 199))


def test_columns_find_shared_prefixes():
    texts = [b"xxabcabcabcyy", b"zzabcabcabcqq", b"abcabcabc"]
    anchors = np.array([2, 2, 0])
    found = {int(o[i]) + int(anchors[i]) * 0 for o, sh in suffix_dedup.sort_columns(texts, anchors, np.zeros(3, int), 9) for i in range(3) if sh[i]}
    assert 2 in found and 0 in found


# ---- html


PAGE = """<!DOCTYPE html><html><head><title>T &amp; t</title><style>p{}</style><script>var a="</p><p>no</p>";</script></head><body>
<header><h1>Site</h1></header><nav><ul><li><a href="/a">Menu</a></li></ul></nav><div id="cookie-notice">We use cookies, yes, a lot of them.</div>
<div class="layout"><div class="sidebar"><p>Aside text, with commas, many, many, commas and words that go on and on.</p></div>
<article class="post"><h1>Head&nbsp;line</h1><p>First   paragraph, with <a href="x">a link</a> &lt;here&gt; &#233;&eacute;.<p>Second <b>bold
para<!-- hidden --></b> text, long enough to count, and more.<ul><li>one</li><li>two</li></ul><div class="ad">Buy now</div><blockquote>Quoted</blockquote>
<form><input name=q>Search</form></article><section class="comments"><p>First! I agree, entirely, with everything, said here, truly.</p></section></div>
<footer>&copy; now</footer></body></html>"""


def test_main_text():
    assert he.main_text(PAGE) == "Head line\nFirst paragraph, with a link <here> éé.\nSecond bold para text, long enough to count, and more.\none\ntwo\nQuoted"


@pytest.mark.parametrize("source, text", [(None, ""), ("", ""), ("no markup, at all", "no markup, at all"), ("<p>a<p>b", "a\nb"), ("<div><div><p>only, this</div>", "only, this"), ("<nav><a>x</a></nav>", ""), ("<p>1 < 2 & 3</p>", "1 < 2 & 3"), ("<div>" * 3000 + "deep, text", "deep, text"), ("<p>cut <b", "cut <b")])
def test_odd_pages(source, text):
    assert he.main_text(source) == text


def test_article_is_found_among_divs():
    body = "".join(f"<p>Sentence number {i}, which is long, and has commas, to make it count for something.</p>" for i in range(6))
    links = "".join(f'<p><a href="/{i}">Some other, linked headline, number {i}</a></p>' for i in range(9))
    got = he.main_text(f"<html><body><div><div>{links}</div><div class='c1'>{body}</div></div></body></html>")
    assert got.count("Sentence number") == 6 and "headline" not in got


def test_extract(spark):
    df = spark.createDataFrame([(1, "u", PAGE), (2, None, None), (1, "u", PAGE)], "page_id long, url string, html string").withColumn("text", F.lit("clash"))
    got = he.extract(df).collect()
    assert Counter((r["page_id"], r["n_chars"]) for r in got) == Counter({(1, len(he.main_text(PAGE))): 2, (2, 0): 1})
    assert he.extract(df.limit(0)).count() == 0


# ---- chat


TRICKY = ["", "plain", "\\", "\\\\n", "</s>", "<\\/s>", "[INST] x [/INST]", "<|user|>\n", "<<SYS>>", "a<", "|", "|>", "</s>\n</s>", "é 漢 \U0001f600", "\\<s>\\", "<s", "\n"]


def test_escaping_is_reversible_and_hides_control_strings():
    for t in TRICKY:
        b = t.encode()
        e = cf.escape(b)
        assert cf.unescape(e) == b
        assert not any(c.encode() in e for c in cf.CONTROL)


def test_chat_round_trip(spark):
    rows = [(c, k, r, t) for c in range(5) for k, (r, t) in enumerate([("user", TRICKY[(3 * c + i) % len(TRICKY)]) if i % 2 == 0 else ("assistant", TRICKY[(5 * c + i) % len(TRICKY)]) for i in range(7)])]
    rows += [(9, None, None, None), (9, 1, "odd |>\n role", "x"), (9, 1, "odd |>\n role", "x"), (None, 0, "user", "nobody")]
    df = spark.createDataFrame(rows, "conv_id long, turn int, role string, text string").withColumn("formatted", F.lit("clash")).repartition(4)
    whole = {r["conv_id"]: r["formatted"] for r in cf.format_conversations(df).collect()}
    got = {r["conv_id"]: r for r in cf.conversation_digests(cf.format_turns(df)).collect()}
    for c in {r[0] for r in rows}:
        turns = sorted(((r[1] is not None, r[1] or 0, r[3] is not None, r[3] or "", r[2] or "") for r in rows if r[0] == c))
        turns = [(x[4], x[3]) for x in turns]
        assert [(a.decode(), b.decode()) for a, b in cf.parse(whole[c].encode())] == turns
        want = hashlib.sha256("".join(f"{a}\n{b}\n" for a, b in turns).encode()).hexdigest()
        said = "".join(b for a, b in turns if a == "assistant")
        r = got[c]
        assert (r["n_turns"], r["turns_sha256"], r["loss_chars"], r["loss_sha256"], r["formatted_chars"]) == (len(turns), want, len(said), hashlib.sha256(said.encode()).hexdigest(), len(whole[c]))
    assert cf.conversation_digests(cf.format_turns(df.limit(0))).count() == 0


def test_chat_blocks(spark, monkeypatch):
    monkeypatch.setattr(cf, "BLOCK", 50)
    df = spark.createDataFrame([(c, k, "assistant", f"text {c} {k} [INST]" * 3) for c in range(3) for k in range(9)], "conv_id long, turn int, role string, text string")
    assert {r["n_turns"] for r in cf.conversation_digests(cf.format_turns(df)).collect()} == {9}


# ---- language


def test_language_id(spark, sf_dir):
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    out = langid.op6_language_id(spark, sf_dir)
    held = out.where("held_out").join(docs.select("doc_id", "lang"), "doc_id")
    assert held.where("lang = lang_pred").count() >= 0.97 * held.count()
    assert out.count() == docs.count() and out.where("score < 0 or score > 1 or lang_pred = 'und'").isEmpty()


def test_language_edges(spark, sf_dir, docs):
    model = langid.train_language_model(spark.read.parquet(f"{sf_dir}/documents.parquet"))
    got = langid.identify(docs.where("doc_id is null or doc_id <> 14"), model).collect()
    for r in got:
        if r["doc_id"] in (7, 8, 9):
            assert (r["lang_pred"], r["score"]) == ("und", 0.0)
    none = langid.identify(docs, None).collect()
    assert {r["lang_pred"] for r in none} <= {"und"}
    assert langid.train_language_model(spark.createDataFrame([], "doc_id long, text string, lang string")) is None


def test_language_sums_do_not_depend_on_blocks(monkeypatch):
    texts = [b"", b"One two", prose(500, 3).encode(), b"x", "Größe über".encode()]
    data, off = np.frombuffer(b"".join(texts), np.uint8), np.concatenate([[0], np.cumsum([len(t) for t in texts])])
    table = np.random.default_rng(0).random((langid.BUCKETS, 3))
    a = langid.document_sums(data, off, table)
    monkeypatch.setattr(langid, "BLOCK", 64)
    b = langid.document_sums(data, off, table)
    for x, y in zip(a, b, strict=True):
        assert np.allclose(x, y)
    lone = langid.document_sums(np.frombuffer(texts[2], np.uint8), np.array([0, len(texts[2])]), table)
    assert np.allclose(lone[0][0], a[0][2])


# ---- quality


def test_quality(spark, sf_dir):
    labels = spark.read.parquet(f"{sf_dir}/labels.parquet")
    out = quality.op2_quality(spark, sf_dir)
    held = out.where("held_out").join(labels, "doc_id").collect()
    assert sum(r["predicted"] == r["quality"] for r in held) >= 0.9 * len(held)
    assert all(r["predicted"] == 1 for r in held if r["quality"] == 1) or sum(r["predicted"] for r in held if r["quality"] == 1) >= 0.95 * sum(r["quality"] for r in held)
    assert out.where("score < 0 or score > 1 or score is null").isEmpty() and out.count() == spark.read.parquet(f"{sf_dir}/documents.parquet").count()


def test_quality_edges(spark, sf_dir, docs):
    labels = spark.createDataFrame([(i, i % 2) for i in range(1, 13)] + [(3, None), (None, 1), (99, 1)], "doc_id long, quality int")
    model = quality.train_quality_model(docs, labels, epochs=3)
    got = quality.score_quality(docs, model).collect()
    assert len(got) == docs.count() and all(0 <= r["score"] <= 1 for r in got)
    empty = {round(r["score"], 9) for r in got if r["doc_id"] in (7, 8, 9)}
    assert len(empty) <= 1
    kept = quality.keep_quality(docs, model)
    assert kept.columns == docs.columns and kept.count() == sum(r["predicted"] for r in got)
    assert quality.train_quality_model(docs, labels.limit(0)) is None
    assert {r["score"] for r in quality.score_quality(docs, None).collect()} <= {0.5}


def test_gradients():
    r = np.random.default_rng(0)
    bags = quality.Bags(r.normal(size=(9, 4)), np.array([0, 0, 0, 1, 1, 3, 3, 3, 3]), 4)
    y, w = np.array([1.0, 0, 1, 0]), np.array([1.0, 2, 1, 1])
    m = quality.GatedAttention(4, 3, 2)

    def loss():
        p = m.forward(bags)[-1]
        return -(w * (y * np.log(p) + (1 - y) * np.log(1 - p))).sum() / w.sum()

    grad, _ = m.gradients(bags, y, w)
    for k, g in grad.items():
        for i in np.ndindex(m.p[k].shape):
            m.p[k][i] += 1e-5
            up = loss()
            m.p[k][i] -= 2e-5
            down = loss()
            m.p[k][i] += 1e-5
            assert g[i] == pytest.approx((up - down) / 2e-5, abs=1e-6)


def test_passages_do_not_depend_on_blocks(monkeypatch):
    texts = [prose(500, 1).encode(), b"", b"One two.", prose(100, 2).encode()]
    data, off = np.frombuffer(b"".join(texts), np.uint8), np.concatenate([[0], np.cumsum([len(t) for t in texts])])
    x, d = quality.encode_passages(data, off)
    monkeypatch.setattr(quality, "BLOCK", 100)
    y, e = quality.encode_passages(data, off)
    assert (d == e).all() and np.allclose(x, y) and np.bincount(d, minlength=4).tolist() == [8, 0, 1, 2]


# ---- further cases


def test_broadcast_and_shuffled_windows_agree(spark):
    """A benchmark of more windows than literals, probed by broadcast hashes and by shuffled ones."""
    rows = [(i, prose(80, 50 + i)) for i in range(30)] + [(30, PASSAGE), (31, None)]
    items = [(f"b{i}", prose(40, 5000 + i)) for i in range(60)] + [("hit", PASSAGE), ("part", " ".join(prose(80, 55).split()[20:40]))]
    docs, bench = spark.createDataFrame(rows, SCHEMA), spark.createDataFrame(items, "item_id string, text string")
    want = brute_contamination(rows, items)
    for broadcast in (10**6, 0):
        got = dc.contamination(docs, bench, max_literals=5, broadcast=broadcast)
        assert Counter(map(tuple, got.select("doc_id", "n_words", "n_hit", "n_items", "items_sha256", "contaminated").collect())) == want


def test_names_of_own_columns_may_occur(spark):
    """Input columns named like internal ones are passed through or ignored."""
    rows = [(1, "one two three four five six"), (2, "One two three four five six"), (3, PASSAGE)]
    df = spark.createDataFrame(rows, SCHEMA)
    for c in (RID, "__words", "__hits", "__found", "__number", "__all", "__kept", "__place", "row", "digest", "shard", "comp"):
        df = df.withColumn(c, F.lit(0))
    assert ed.exact_dedup(df).count() == 3 and ngram_join.jaccard_components(df).count() == 3
    assert {r["group_size"] for r in ed.exact_dedup(df).collect()} == {1, 2}
    assert sharding.extendible_shards(df).count() == suffix_dedup.remove_repeats(df).count() == 3
    b = spark.createDataFrame([("q", PASSAGE)], "item_id string, text string")
    for literals in (0, 1000):
        for mode, n in (("document", 2), ("span", 3)):
            left = dc.decontaminate(df, b, mode=mode, max_literals=literals)
            assert left.columns == df.columns and left.count() == n


def test_exact_dedup_of_text_ids(spark):
    df = spark.createDataFrame([("b", "X"), ("a", "x"), ("c", "y"), (None, "x")], "doc_id string, text string")
    for keep, first in (("largest", "b"), ("smallest", "a")):
        got = {(r["doc_id"], r["keep_id"], r["group_size"], r["kept"]) for r in ed.exact_dedup(df, keep=keep).collect()}
        assert got == {("a", first, 3, first == "a"), ("b", first, 3, first == "b"), (None, first, 3, False), ("c", "c", 1, True)}


def test_write_shards_keeps_every_row(spark, tmp_path):
    df = spark.createDataFrame([(1, "a" * 50), (1, "b" * 50), (None, "c" * 50)], SCHEMA).withColumn("shard", F.lit("own"))
    sharding.write_shards(df, str(tmp_path / "out"), limit=60)
    back = spark.read.parquet(str(tmp_path / "out"))
    assert Counter((r["doc_id"], r["text"], r["shard"]) for r in back.collect()) == Counter((r["doc_id"], r["text"], "own") for r in df.collect())


def test_training_rows_are_bounded_where_ids_repeat(spark):
    """Rows that share a labelled id: at most max_rows distinct texts are learnt from."""
    df = spark.range(3000).select(F.lit(1).cast("long").alias("doc_id"), F.concat(F.lit("some text number "), F.col("id") % 500).alias("text"), F.when(F.col("id") % 2 == 0, "en").otherwise("de").alias("lang"))
    labels = spark.createDataFrame([(1, 1)], "doc_id long, quality int")
    seen = []
    keep, quality.GatedAttention.fit = quality.GatedAttention.fit, lambda self, x, doc, y, **k: seen.append(len(y)) or self
    fit, langid.fit = langid.fit, lambda data, **k: seen.append(len(data))
    try:
        quality.train_quality_model(df, labels, max_rows=40)
        langid.train_language_model(df, max_rows=30)
    finally:
        quality.GatedAttention.fit, langid.fit = keep, fit
    assert seen == [40, 30]


@pytest.mark.parametrize("limits", [(5000, 20_000), (50, 60), (50, 7)])
def test_one_line_in_many_different_texts(spark, monkeypatch, limits):
    """Texts that share a line shorter than the length remove nothing; a longer line goes from all of them."""
    monkeypatch.setattr(suffix_dedup, "SPLIT", limits[0])
    monkeypatch.setattr(suffix_dedup, "COLLECTION", limits[1])
    r = np.random.default_rng(9)
    letters = np.array(list("abcdefghijklmnopqrstuvwxyz "))
    own = lambda n: "".join(letters[r.integers(0, 27, n)])
    short, line = own(150), own(230)
    rows = [(i, own(300) + short + own(300)) for i in range(200)] + [(1000 + i, own(200) + line + own(250)) for i in range(100)]
    docs = spark.createDataFrame(rows, SCHEMA).repartition(4)
    got = {x["doc_id"]: (x["n_removed"], x["n_spans"]) for x in suffix_dedup.remove_repeats(docs).collect()}
    for i, t in rows:
        if i < 1000:
            assert got[i] == (0, 0)
        else:
            at = t.index(line)
            a, b = got[i]
            assert b == 1 and 230 <= a <= 236, (at, a)


PLAIN = "<p>" + "This paragraph is long, has commas, and is the text of the page. " * 4 + "</p>"


@pytest.mark.parametrize("wrap", [
    '<div class="content no-sidebar">%s</div>', '<div class="with-comments hasSidebar">%s</div>', '<div data-hidden="false" data-id="related-12">%s</div>', "<div data-class='ad'>%s</div>", '<article><div class="menu-item-description">%s</div></article>',
    '<div class="page sidebar-right"><div id="main">%s</div></div>', '<div class="cookie-recipe">%s</div>', '<article class="post related">%s</article>', "<div class=content><div class='without-ads'>%s</div></div>",
])
def test_layout_names_do_not_hide_the_article(wrap):
    for around in ("%s", '<div class="main-nav"><a href="/">Home</a></div>%s<div id="site-footer"><p>Imprint, all rights reserved.</p></div><div class="related-posts"><p>Other page, read it.</p></div>'):
        assert he.main_text("<html><body>" + around % (wrap % (PLAIN + PLAIN)) + "</body></html>") == "\n".join([he.main_text(PLAIN)] * 2)


def test_inline_furniture_and_comments_go():
    text = he.main_text(PLAIN)
    page = f'<article>{PLAIN}<p>Go on, <a class="share" href="x">Share <b>this</b></a>and <span class="ad">an <span>inner</span> advert</span>end, at last.</p></article>'
    assert he.main_text(page) == text + "\nGo on, and end, at last."
    many = "".join(f"<p>Reader {i} says, in many words, that all of it is very good.</p>" for i in range(40))
    assert he.main_text(f'<div id="main">{PLAIN}{PLAIN}</div><div class="comment-list">{many}</div>') == text + "\n" + text


def test_trees_give_the_pairs_of_the_join(monkeypatch):
    """At small sizes too, pairs come out of searches of an R-tree, and every link is among them."""
    search, got = ngram_join.CountRTree.search_all, []
    rows = near_copies(11, 6, 8)
    t = Fraction(3, 4)

    def counted(self, *args):
        out = search(self, *args)
        got.append(len(out[0]))
        return out

    monkeypatch.setattr(ngram_join.CountRTree, "search_all", counted)
    from codetrees.llm.textbytes import shingles

    sets = [shingles(np.frombuffer(x.encode(), np.uint8)) for _, x in rows]
    v = [ngram_join.count_vector(s) for s in sets]
    n = len(rows)
    yes = np.ones(n, bool)
    b = ngram_join.Blocks([np.arange(n), np.arange(n), np.array([len(s) for s in sets]), np.stack([x[0] for x in v]), np.array([x[1] for x in v]), yes, yes, ~yes], np.zeros(n, np.int64), t)
    covers, still = b.covers()
    assert got and len(covers[0]) < n  # at most one pair a node
    pairs = {(int(i), int(j)) for i, j, _ in b.crossing(False).T}
    want = {(i, j) for i in range(n) for j in range(i + 1, n) if (o := ngram_join.overlap(sets[i], sets[j])) >= ngram_join.needed_overlap(len(sets[i]), len(sets[j]), t) and o}
    assert want <= pairs
    told = {(int(i), int(j)) for i, j, _ in covers.T}
    told |= {(j, i) for i, j in told}
    assert all(still[i] and still[j] for i, j in pairs - told)  # what covers leave open is open


@pytest.mark.parametrize("n", [1, 2047, 2048, 2730, 2731, 8191, 8192, 20_000, 100_000])
def test_linked_sizes_share_a_class(n):
    t = Fraction(3, 4)
    s = np.sort(rng.integers(0, 1 << 63, n).astype(np.uint64))
    own = {p["cls"] for p in ngram_join.points_of(s, t)}
    for m in {-(-3 * n // 4), n, min(n + n // 3, 4 * n // 3)}:
        other = {ngram_join.size_class(max(m, 1)), ngram_join.size_class(-(-3 * max(m, 1) // 4))}
        assert own & other
