"""Corpus operators against brute force on small tables with edge rows."""

import hashlib
import math
import random
import re
import zlib
from collections import Counter, defaultdict

import numpy as np
import pytest
from pyspark.sql import functions as F

from dictparse.llm import decontamination, html_extraction, knn, line_dedup, near_dedup, packing, repeats, sharding, token_counts, toxicity

SCHEMA = "doc_id long, text string, lang string, source string, n_chars long, doc string, id long, h1 long"


def table(spark, rows):
    """Documents with further columns whose names clash with ones used inside."""
    return spark.createDataFrame([(i, t, "en", "s", None if t is None else len(t), "x", 1, 2) for i, t in rows], SCHEMA)


def words(rng, n, size=400):
    return " ".join(f"w{rng.randrange(size)}" for _ in range(n))


@pytest.fixture(scope="module")
def rows():
    rng = random.Random(5)
    base = words(rng, 120)
    out = [(k, words(rng, rng.randrange(1, 150), 3000)) for k in range(40)]
    for k in range(40, 70):  # near copies
        w = base.split()
        for _ in range(rng.randrange(0, 12)):
            w[rng.randrange(len(w))] = f"x{rng.randrange(10**6)}"
        out.append((k, " ".join(w)))
    passage = "A passage that comes in many documents, " * 7
    out += [(k, words(rng, 30, 3000) + "\n" + passage + "\n" + words(rng, 20, 3000)) for k in range(70, 80)]
    out += [(80, None), (81, ""), (82, "one"), (83, "One"), (84, "a" * 1500), (85, "é" * 400), (86, base), (86, base), (87, "\n\n  \n"), (None, base), (None, None), (88, words(rng, 20_000, 10**6)), (89, "ab " * 700)]
    return out


def test_empty_tables(spark):
    none = table(spark, []).where("false")
    assert sharding.shard_documents(none).count() == 0
    assert line_dedup.drop_repeated_lines(none).count() == 0
    assert near_dedup.near_duplicates(none).count() == 0
    assert near_dedup.keep_first(none).count() == 0
    assert repeats.repeats(none).count() == 0
    assert packing.pack_documents(none).count() == 0
    assert token_counts.count_tokens(none).count() == 0
    items = spark.createDataFrame([], "item_id long, text string")
    assert decontamination.mark(none, items).count() == 0
    assert toxicity.scored(none, spark.createDataFrame([], "doc_id long, toxic int")).count() == 0
    assert html_extraction.extract(spark.createDataFrame([], "page_id long, url string, html string")).count() == 0
    assert knn.top_k(spark.createDataFrame([], "vec_id long, embedding array<float>"), "id % 50 = 0").count() == 0


# ---- html


def test_main_text_of_one_page():
    page = """<html><head><title>x</title></head><body><header class="top">Site</header><div id="nav-bar">Menu</div><div class="cookie-notice">We use</div>
<main class="has-sidebar"><article><header><h1>T &amp; U</h1></header><p>One<br>two  <b>bo</b>ld<p>Three<ul><li>a<li>b</ul><aside>side</aside><form><input>f</form>
<div class="ad-slot">buy</div><section class="comments"><article class="comment">no</article></section></article></main><footer>f</footer><script>if(a<b && c="</p>){}</script></body>"""
    assert html_extraction.Page(page).text() == "T & U\nOne two bold\nThree\na\nb"
    assert html_extraction.Page("").text() == ""
    assert html_extraction.Page("plain &lt;b&gt; <unclosed").text().startswith("plain <b>")


def test_template_words_go_and_content_stays(spark):
    def page(k):
        return f'<html><body><div class="x1"><span>Home</span> <span>Contact</span></div><div class="x2"><p>Story {k} of {k * 7} things</p></div><div class="x3"><i>Imprint</i></div></body></html>'

    rows = [(k, f"https://a.example/{k}", page(k)) for k in range(8)]
    rows += [(20 + k, f"https://b.example/{k}", page(1)) for k in range(8)]  # copies are no template
    rows += [(40, None, None), (41, "https://a.example/x", ""), (42, "::", "<p>alone</p>")]
    got = {r.page_id: r for r in html_extraction.extract(spark.createDataFrame(rows, "page_id long, url string, html string")).collect()}
    assert got[3].text == "Story 3 of 21 things" and got[3].n_chars == len(got[3].text)
    assert got[21].text == "Home Contact\nStory 1 of 7 things\nImprint"
    assert got[40].text == "" and got[41].text == "" and got[42].text == "alone"


def test_template_words_inside_articles_go(spark):
    def page(k, n):
        notice = "<div class='x9'><p>Sent to <b>all</b> readers</p></div>"
        return f"<html><body><p>Top</p><article><h1>Daily</h1>{notice}{'<p>more of it</p>' * (k % 3)}<p>Story {k} of {n}</p><p>By staff</p></article></body></html>"

    rows = [(k, f"https://a.example/{k}", page(k, k * 7)) for k in range(10)] + [(20 + k, f"https://b.example/{k}", page(1, 7)) for k in range(8)]
    # a word that each page holds once, but now before and now after the others, is none of the frame's
    moved = [f"<html><body>{'loose' * (k % 2)}<div><i>Home</i></div><div><u>{k}</u></div>{'loose' * (k % 2 == 0)}</body></html>" for k in range(10)]
    rows += [(40 + k, f"https://c.example/{k}", x) for k, x in enumerate(moved)]
    got = {r.page_id: r.text for r in html_extraction.extract(spark.createDataFrame(rows, "page_id long, url string, html string")).collect()}
    for k in range(10):
        assert got[k] == "\n".join(["more of it"] * (k % 3) + [f"Story {k} of {k * 7}"])
        assert got[40 + k] == (f"loose\n{k}" if k % 2 else f"{k}\nloose")
    assert got[20] == "Daily\nSent to all readers\nmore of it\nStory 1 of 7\nBy staff"  # copies are no template


def test_templates_of_any_size_and_number_reach_their_pages(spark, monkeypatch):
    def page(k, frame):
        return f"<html><body><div><i>{frame}</i></div><div><p>Story {k} of {k * 7} things</p></div></body></html>"

    large = " ".join(f"boilerplate{k}" for k in range(40_000))  # a template of over 1 MiB
    rows = [(k, f"https://large.example/{k}", page(k, large)) for k in range(6)]
    rows += [(100 + 10 * h + k, f"http://h{h}.example:80/{k}", page(k, "Home Contact")) for h in range(5) for k in range(6)]
    rows += [(200 + k, "No.Scheme/x", page(k, "Imprint")) for k in range(6)] + [(300, None, None)]
    pages = spark.createDataFrame(rows, "page_id long, url string, html string")
    expected = sorted((i, f"Story {i % 10 if i >= 100 else i} of {(i % 10 if i >= 100 else i) * 7} things" if i != 300 else "") for i, _, _ in rows)
    for hosts, size in ((200_000, 16 << 20), (2, 16 << 20), (200_000, 1000)):
        monkeypatch.setattr(html_extraction, "MAX_SENT", hosts)
        monkeypatch.setattr(html_extraction, "MAX_BYTES", size, raising=False)
        assert sorted((r.page_id, r.text) for r in html_extraction.extract(pages).collect()) == expected


def test_pages_of_the_smallest_tables(spark, duck):
    import html as entities

    got = {r.page_id: r.text for r in html_extraction.op1_html_extraction(spark, "/root/testdata/sf0.001").collect()}
    for page_id, source in duck.execute("SELECT page_id, html FROM pages").fetchall():
        article = re.search("<article>(.*?)</article>", source, re.S)[1]
        blocks = (re.sub(r"\s+", " ", entities.unescape(re.sub("<[^>]*>", "", b.replace("<br>", " ")))).strip() for b in re.split("</?(?:p|h1)>", article))
        assert got[page_id] == "\n".join(b for b in blocks if b)


# ---- decontamination


def brute_hits(text, items, window=10):
    w = decontamination.words((text or "").encode())
    hit, found = set(), set()
    for name, t in items:
        iw = decontamination.words((t or "").encode())
        size = min(window, len(iw))
        for k in range(len(iw) - size + 1 if size else 0):
            for at in range(len(w) - size + 1):
                if w[at : at + size] == iw[k : k + size]:
                    hit |= set(range(at, at + size))
                    found.add(name)
    return len(w), len(hit), sorted(map(str, found))


def test_decontamination(spark, rows):
    rng = random.Random(9)
    pool = [t for _, t in rows if t and 30 < len(t.split()) < 500]
    items = [(k, " ".join(rng.choice(pool).upper().split()[5:25])) for k in range(6)] + [(6, "one"), (7, None), (8, "!!"), (9, "w1 W2"), (10, words(rng, 40))]
    bench = spark.createDataFrame(items, "item_id long, text string")
    docs = table(spark, rows)
    got = sorted((-1 if r.doc_id is None else r.doc_id, r._n_words, sum(r._spans[1::2]) - sum(r._spans[::2]), [*r._items]) for r in decontamination.mark(docs, bench).collect())
    assert got == sorted((i if i is not None else -1, *brute_hits(t, items)) for i, t in rows)
    clean = decontamination.decontaminate(docs, bench)
    assert clean.columns == docs.columns
    clashing = decontamination.decontaminate(docs.select("*", F.lit("own").alias("_spans"), F.lit("own").alias("_Items")), bench)
    assert clashing.where("_spans = 'own' AND _items = 'own'").count() == clean.count()
    assert clean.count() == sum(brute_hits(t, items)[1] == 0 for _, t in rows)
    old, decontamination.BLOCK_BYTES = decontamination.BLOCK_BYTES, 100  # items in blocks
    try:
        assert sorted((-1 if r.doc_id is None else r.doc_id, r._n_words, sum(r._spans[1::2]) - sum(r._spans[::2]), [*r._items]) for r in decontamination.mark(docs, bench).collect()) == got
    finally:
        decontamination.BLOCK_BYTES = old


@pytest.mark.parametrize("window", [3, 10, 40])
def test_longest_matches(window):
    rng = random.Random(window)
    texts = [[b"abc"[k : k + 1] for k in (rng.randrange(3) for _ in range(n))] for n in (150, 0, 1, 300)]
    texts.append(texts[0][20:120] + [b"z"] + texts[3][:90])
    shard = decontamination.Shard(texts, window)
    seq = shard.words.tolist()
    assert [seq[i : i + window] for i in shard.order] == sorted(seq[i : i + window] for i in range(len(seq)))
    test = [texts[0][10:100], [b"y"] + texts[3][40:81] + [b"y"], texts[3][7:9], [], [b"q"] * 50]
    items = decontamination.Items([(str(k), b" ".join(t)) for k, t in enumerate(test)], window)
    expected = set()
    for k, t in enumerate(test):
        for r, own in enumerate(texts):
            for a in range(len(t)):
                for b in range(len(own)):
                    if t[a] == own[b] and (not a or not b or t[a - 1] != own[b - 1]):
                        n = 0
                        while a + n < len(t) and b + n < len(own) and t[a + n] == own[b + n]:
                            n += 1
                        if n >= min(window, len(t)):
                            expected.add((k, a, int(shard.starts[r]) + b, n))
    assert {*zip(*(x.tolist() for x in decontamination.longest_matches(shard, items)), strict=True)} == expected


# ---- token counts


def test_token_counts(spark, rows):
    import public_tokenizers
    import regex

    score = token_counts.scores()

    def best(word):
        top = [(0, 0)]
        for end in range(1, len(word) + 1):
            top.append(max((top[start][0] + score[word[start:end]], top[start][1] - 1) for start in range(end) if word[start:end] in score))
        return -top[-1][1]

    few = [r for r in rows if r[1] is None or len(r[1]) < 400]
    got = sorted(((r.doc_id if r.doc_id is not None else -1), r.n_tokens) for r in token_counts.count_tokens(table(spark, few)).collect())
    split = regex.compile(public_tokenizers.PATTERN).findall
    assert got == sorted((i if i is not None else -1, sum(best(w.encode()) for w in split(t or ""))) for i, t in few)
    trie = token_counts.Trie(score)
    trie.counts([b"abcdef", b"abcxyz", b"abc"])
    assert trie.nodes == 9  # shared prefixes are walked once


# ---- sharding


def jump_brute(key, shards):
    key &= (1 << 64) - 1
    b, j = -1, 0
    while j < shards:
        b = j
        key = (key * 2862933555777941757 + 1) & (1 << 64) - 1
        j = int((b + 1) * ((1 << 31) / ((key >> 33) + 1)))
    return b


def test_sharding(spark, rows):
    many = rows + [(7, "same")] * 5000
    got = sharding.shard_documents(table(spark, many)).collect()
    assert len(got) == len(many)
    assert Counter((r.doc_id, r.size, r.text_crc32) for r in got) == Counter((i, len((t or "").encode()) + 1, zlib.crc32((t or "").encode())) for i, t in many)
    slots = defaultdict(list)
    for r in got:
        slots[r.shard].append(r.slot)
        assert r.shard == jump_brute(r.doc_id or 0, 8) and r.grown_shard == jump_brute(r.doc_id or 0, 9) and r.grown_shard in (r.shard, 8)
    assert all(sorted(s) == [*range(len(s))] for s in slots.values())
    order = lambda r: (r.doc_id is not None, r.doc_id or 0, r.size, r.text_crc32)
    for s in slots:
        inside = sorted((r for r in got if r.shard == s), key=lambda r: r.slot)
        assert [order(r) for r in inside] == sorted(order(r) for r in inside)
    keys = np.random.default_rng(1).integers(-(1 << 62), 1 << 62, 4000)
    assert sharding.jump(keys, 100).tolist() == [jump_brute(int(k), 100) for k in keys]


# ---- repeats


def brute_repeats(rows, length):
    data = [(i, (t or "").encode()) for i, t in rows]
    count = Counter(x[k : k + length] for _, x in data for k in range(len(x) - length + 1))
    out = []
    for i, x in data:
        gone = bytearray(len(x))
        for k in range(len(x) - length + 1):
            if count[x[k : k + length]] > 1:
                gone[k : k + length] = b"\1" * length
        out.append((i if i is not None else -1, len(x), sum(gone), len(re.findall(b"\1+", bytes(gone))), hashlib.sha256(bytes(b for b, g in zip(x, gone, strict=True) if not g)).hexdigest()))
    return sorted(out)


@pytest.mark.parametrize("length", [200, 60])
def test_repeats(spark, rows, length):
    few = [r for r in rows if r[0] != 88]
    got = sorted((r.doc_id if r.doc_id is not None else -1, r.n_bytes, r.n_removed, r.n_spans, r.kept_sha256) for r in repeats.repeats(table(spark, few), length=length).collect())
    assert got == brute_repeats(few, length)


def test_corpus_order():
    rng = random.Random(2)
    for text in (b"", b"a", b"ab" * 300, bytes(rng.randrange(97, 100) for _ in range(700)), bytes(rng.randrange(256) for _ in range(500)) * 2):
        assert repeats.corpus_order(text, 4, 8).tolist() == sorted(range(len(text)), key=lambda k: text[k:])


# ---- packing


def test_packing(spark, rows):
    from tokenizers import Tokenizer

    import public_tokenizers

    t = Tokenizer.from_file(public_tokenizers.path("byte_bpe_50k.json"))
    t.encode_special_tokens = True
    many = rows + [(200 + k, "<|endoftext|> " + "word " * (k % 300)) for k in range(300)]
    got = packing.pack_documents(table(spark, many)).collect()
    expected = Counter()
    for i, text in many:
        ids = np.array([*t.encode(text or "", add_special_tokens=False).ids, 2], "<u4")
        for k, (start, size) in enumerate(packing.cut(len(ids), 1024)):
            expected[i, k, start, size, zlib.crc32(ids[start : start + size].tobytes())] += 1
    assert Counter((r.doc_id, r.piece, r.start, r.length, r.ids_crc32) for r in got) == expected
    places = defaultdict(list)
    for r in got:
        places[r.sequence_id].append((r.offset, r.length))
    for own in places.values():
        at = 0
        for offset, size in sorted(own):
            assert offset == at
            at += size
        assert at <= 1024
    total = sum(r.length for r in got)
    assert len(places) <= math.ceil(total / 1024) + 2
    joined = {r.sequence_id: len(r.ids) for r in packing.sequences(table(spark, many)).collect()}
    assert joined == {s: sum(n for _, n in own) for s, own in places.items()}


def test_plan_is_best_fit_decreasing():
    rng = random.Random(4)
    for capacity, pieces in [(64, 500), (64, 30), (20, 200), (1024, 400)] + [(50, 40)] * 40:
        counts = Counter(rng.randrange(1, capacity + 1) for _ in range(pieces))
        steps = packing.plan(dict(counts), capacity)
        used = Counter()
        for size, first_rank, ranks, first, offset in steps:
            for k in range(ranks):
                assert used[first + k] == offset
                used[first + k] += size
                assert used[first + k] <= capacity
        assert Counter({s: sum(n for size, _, n, _, _ in steps if size == s) for s in counts}) == counts
        gaps = []  # plain best fit, the longest first
        for size in sorted(counts.elements(), reverse=True):
            fits = [g for g in gaps if g >= size]
            if fits:
                gaps.remove(min(fits))
            gaps.append((min(fits) if fits else capacity) - size)
        assert Counter(capacity - n for n in used.values()) == Counter(gaps)


# ---- kNN


def test_knn(spark, monkeypatch):
    rng = np.random.default_rng(0)
    data = [(k, [float(x) for x in rng.normal(0, 0.2, 8)]) for k in range(400)]
    data += [(k, data[0][1]) for k in range(400, 460)] + [(500, None), (501, [1.0] * 7 + [None]), (502, [float("nan")] * 8), (503, [1.0] * 3), (550, []), (None, data[1][1]), (399, data[399][1]), (50, data[7][1]), (50, data[50][1])]
    usable = [(i, np.pad(np.floor(256 * np.array(v, np.float32).astype(np.float64)).astype(np.int64), (0, 8 - len(v)))) for i, v in data if i is not None and v is not None and all(x is not None and math.isfinite(x) for x in v)]
    expected = []
    for a, (q, v) in enumerate(usable):
        if q % 50 == 0:
            top = sorted((-int(v @ w), i) for b, (i, w) in enumerate(usable) if a != b)[:5]
            expected += [(q, k, i, -s) for k, (s, i) in enumerate(top, 1)]
    table = spark.createDataFrame([(i, v, 1, "x") for i, v in data], "vec_id long, embedding array<float>, row long, cell string")
    for cell, block, part in ((4096, 512, 20_000), (40, 2, 30)):  # one cell; many cells, blocks and parts
        monkeypatch.setattr(knn, "CELL", cell)
        monkeypatch.setattr(knn, "BLOCK", block)
        monkeypatch.setattr(knn, "PART", part)
        assert sorted((r.query_id, r["rank"], r.id, r.score) for r in knn.top_k(table, "id % 50 = 0").collect()) == sorted(expected)
    two = knn.top_k(spark.createDataFrame(data[:3], "vec_id long, embedding array<float>"), "id % 50 = 0").collect()
    assert len(two) == 2


# ---- toxicity


def test_toxicity_finds_held_out_cases(spark):
    rng = random.Random(8)
    bad = ["grobian", "lumpen", "scuzzy", "vexling"]
    rows, labels = [], []
    for k in range(600):
        text = words(rng, rng.randrange(5, 80), 500).split()
        toxic = k % 5 == 0
        for _ in range(3 * toxic):
            text.insert(rng.randrange(len(text)), rng.choice(bad))
        rows.append((k, " ".join(text)))
        labels.append((k, int(toxic)))
    rows += [(1000, None), (1001, ""), (1001, "")]
    marks = spark.createDataFrame(labels + [(None, 1), (5000, 1)], "doc_id long, toxic int")
    got = {r.doc_id: r._score for r in toxicity.scored(table(spark, rows), marks).collect()}
    held = [k for k in range(600) if zlib.crc32(str(k).encode()) % 5 == 0]
    assert np.mean([(got[k] >= 0.5) == (k % 5 == 0) for k in held]) > 0.97
    assert got[1000] == got[1001] < 0.5 and all(0 <= s <= 1 for s in got.values())
    clashing = table(spark, rows).select("*", F.lit(7).alias("_Score"), F.lit(8).alias("_y"), F.lit(9).alias("own"))
    kept = toxicity.drop_toxic(clashing, marks)
    assert kept.columns == clashing.columns and kept.where("_score <> 7 OR _y <> 8 OR own <> 9").count() == 0
    assert sorted(r.doc_id for r in kept.collect()) == sorted(i for i, _ in rows if got[i] < 0.5)


def test_toxicity_on_held_out_rows_of_a_given_table(spark, duck):
    sf = "/root/testdata/sf0.01"
    truth = dict(duck.execute(f"SELECT doc_id, max(toxic) FROM '{sf}/labels.parquet' WHERE toxic IS NOT NULL GROUP BY doc_id").fetchall())
    rows = [r for r in toxicity.op8_toxicity(spark, sf).collect() if r.held_out and r.doc_id in truth]
    toxic, clean = ([r for r in rows if truth[r.doc_id] == y] for y in (1, 0))
    caught, false = sum(r.predicted for r in toxic), sum(r.predicted for r in clean)
    auc = np.mean([(t.score > c.score) + 0.5 * (t.score == c.score) for t in toxic for c in clean])
    print(f"held out {len(rows)}, toxic {len(toxic)}, AUC {auc:.3f}, precision {caught / max(1, caught + false):.3f}, recall {caught / len(toxic):.3f}")
    assert auc > 0.9 and caught >= 0.8 * (caught + false) and caught >= 0.6 * len(toxic)


def test_votes_from_words_and_beginnings():
    rng = random.Random(6)
    texts = [" ".join(rng.choice(["grob", "grobian", "Grobians!!", "lumpen", "lumpenpack", "idiot", "SCUM", "fine", "und", "x"]) for _ in range(rng.randrange(12))) for _ in range(300)]
    hasher = toxicity.Hasher()
    features = [hasher.features(t) for t in texts]
    every = np.unique(np.concatenate(features))
    learned = set(rng.sample(every.tolist(), 14))
    votes = toxicity.Votes(np.array(sorted(learned), np.uint64))
    fixed = set(toxicity.insult_hashes().tolist())
    for t, own in zip(texts, (f.tolist() for f in features), strict=True):
        bits = int(any(x in fixed for x in own))
        for x in own:
            if x in learned:
                bits |= 1 << 1 + (x & 3) * toxicity.SPLIT + (x >> 7) % toxicity.SPLIT
        last = 1 + toxicity.KINDS * toxicity.SPLIT
        assert votes.pattern(t) % (1 << last) == bits
        words, insults = sum(x in learned and not x & 3 for x in own), sum(x in fixed for x in own)
        assert votes.pattern(t) >> last == (words >= 2) + 2 * (words >= 4) + 4 * (insults >= 2 or (words > 0 and "!!" in t)) + 8 * (words > 0 and "SCUM" in t)


def test_training_rows_are_voted_on_whole_texts(spark, monkeypatch):
    seen = []
    monkeypatch.setattr(toxicity, "Linear", lambda features, patterns, target: seen.append((features, patterns)))
    rng = random.Random(3)
    rows = [(k, " ".join("".join(rng.choices("abcdefghijklmnop", k=7)) for _ in range(40)) + (" grobian!! GROSS" if k % 4 == 0 else " fine!! GREAT")) for k in range(200)]
    _, model, _ = toxicity.fit(table(spark, rows), spark.createDataFrame([(k, int(k % 4 == 0)) for k in range(200)], "doc_id long, toxic int"))
    ((features, patterns),) = seen
    last = 1 + toxicity.KINDS * toxicity.SPLIT
    used = [k for k in range(200) if zlib.crc32(str(k).encode()) % 5]
    assert len(features) == len(patterns) == len(used)
    for bit in (last + 2, last + 3):  # exclamation marks and capitals beside a word of the lexicon
        assert (patterns >> bit & 1).sum() == sum(k % 4 == 0 for k in used)


def test_lexicon_counts_all_labelled_rows_and_near_copies_once(spark):
    rng = random.Random(12)
    rows = [(k, " ".join(f"{rng.choice('abcdefgh')}{rng.randrange(400)}" for _ in range(12)) + (" lumpen" if k % 7 == 0 else "")) for k in range(900)]
    rows += [(k, "copied words about vexling") for k in range(1000, 1200)]
    toxic = {k: int(k % 7 == 0 or k >= 1000) for k, _ in rows}
    docs = table(spark, rows + rows[:50] + [(2000, None), (2001, "")])
    labelled = toxicity.labelled_rows(docs, spark.createDataFrame([*toxic.items(), (2000, 0), (2001, 0), (None, 1)], "doc_id long, toxic int"), "doc_id", "text", "toxic")
    expected = Counter()
    for k, t in rows + rows[:50] + [(2000, ""), (2001, "")]:
        if zlib.crc32(str(k).encode()) % 5:
            for f in toxicity.Hasher().features(t).tolist():
                expected[f, "total"] += 1
                expected[f, "hits"] += toxic.get(k, 0)
    counted = {r.f % (1 << 64): (r.total, r.hits) for r in toxicity.feature_counts(labelled, 500).collect()}
    assert counted == {f: (expected[f, "total"], expected[f, "hits"]) for f, _ in expected}
    lexicon, prior = toxicity.learned_lexicon(labelled)
    known = lambda w: toxicity.Hasher().features(w)[0] in lexicon
    assert known("lumpen") and not known("vexling") and not known("copied")
    assert toxicity.learned_lexicon(labelled, most=1)[0].tolist() == lexicon[:1].tolist()
    used = [k for k, _ in rows + rows[:50] if zlib.crc32(str(k).encode()) % 5] + [k for k in (2000, 2001) if zlib.crc32(str(k).encode()) % 5]
    assert prior == sum(toxic.get(k, 0) for k in used) / len(used)


def test_without_labels_the_fixed_lexicon_votes(spark):
    none = spark.createDataFrame([], "doc_id long, toxic int")
    assert toxicity.scored(table(spark, [(1, "fine words"), (2, None)]), none).count() == 2


# ---- lines


def brute_lines(rows):
    strip = lambda x: re.sub("[A-Z]", lambda m: m[0].lower(), x.strip(" \t\n\x0b\x0c\r"))
    least = -(1 << 63)
    held = defaultdict(set)
    for i, t in rows:
        for line in (t or "").split("\n"):
            held[strip(line)].add(least if i is None else i)
    out = []
    for i, t in rows:
        lines = (t or "").split("\n")
        kept = [x for x in lines if len(strip(x)) < 20 or len(held[strip(x)]) < 3 or max(held[strip(x)]) == (least if i is None else i)]
        out.append((i if i is not None else -1, len(lines), len(lines) - len(kept), "\n".join(kept)))
    return sorted(out)


def test_line_dedup(spark, rows):
    many = rows + [(300 + k, f"  A LINE that many documents have \t\n{'x' * (18 + k % 3)}\nown {k}\n\n") for k in range(12)] + [(311, "a line that many documents have")]
    got = sorted((r.doc_id if r.doc_id is not None else -1, r._n_lines, r._n_dropped, r._kept) for r in line_dedup.drop_repeated_lines(table(spark, many)).collect())
    assert got == brute_lines(many)
    clashing = table(spark, many).select("*", *(F.lit(k).alias(c) for k, c in enumerate(("_doc", "_lines", "_stay", "_KEPT", "_n_lines", "drops", "batch", "h2"))))
    wide = line_dedup.drop_repeated_lines(clashing)
    assert wide.columns[:-3] == clashing.columns and wide.where("_doc <> 0 OR _stay <> 2 OR drops <> 5").count() == 0
    assert sorted((r.doc_id if r.doc_id is not None else -1, r[-2], r[-1], r[-3]) for r in wide.collect()) == got


def test_line_runs_hold_a_key_once(spark):
    spans = [(0, 10), (5, 15), (12, 20), (0, 3), (30, 31)]
    runs = line_dedup.LineRuns(spark, fanout=2)
    for n, (lo, hi) in enumerate(spans):
        runs.add(spark.createDataFrame([(k, k, n) for k in range(lo, hi)], "h1 long, h2 long, doc long"))
        held = [r.h1 for run in runs.runs() for r in run.collect()]
        assert sorted(held) == sorted({k for a, b in spans[: n + 1] for k in range(a, b)})  # the anti-join lets no key in twice
    assert len(runs.runs()) < 5
    assert {(r.h1, r.max_doc) for r in runs.repeated(2).collect()} == {(k, 3) for k in range(3)} | {(k, 1) for k in range(5, 10)} | {(k, 2) for k in range(12, 15)}


# ---- near duplicates


def brute_components(rows, width):
    least = -(1 << 63)
    named = [(least if i is None else i, t) for i, t in rows]
    sets = []
    for _, t in named:
        w = [x for x in re.split(r"[\x20\x09-\x0D]+", re.sub("[A-Z]", lambda m: m[0].lower(), t or "")) if x]
        sets.append({tuple(w[k : k + width]) for k in range(max(1, len(w) - width + 1))} if w else set())
    root = {i: i for i, _ in named}

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    for a in range(len(named)):
        for b in range(a):
            both = len(sets[a] & sets[b])
            if sets[a] and sets[b] and 100 * both >= 80 * (len(sets[a]) + len(sets[b]) - both):
                x, y = find(named[a][0]), find(named[b][0])
                root[max(x, y)] = min(x, y)
    back = lambda x: -1 if x == least else x
    # an empty text is linked with nothing
    return sorted((back(i), len(s), back(find(i) if s else i)) for (i, _), s in zip(named, sets, strict=True))


@pytest.mark.parametrize("width", [2, 5])
def test_near_duplicates(spark, rows, width):
    got = sorted((r.doc if r.doc is not None else -1, r.n, r.component if r.component is not None else -1) for r in near_dedup.near_duplicates(table(spark, rows), width=width).collect())
    assert got == brute_components(rows, width)


def test_words_whose_polynomial_hashes_collide_are_apart(spark):
    word = "a"
    while len(word) < 2048:  # a Thue-Morse word and its complement: equal under any polynomial modulo 2 ** 64
        word += word.translate({97: 98, 98: 97})
    docs = table(spark, [(1, word), (2, word.translate({97: 98, 98: 97})), (3, word.upper())])
    assert {r.doc: r.component for r in near_dedup.near_duplicates(docs).collect()} == {1: 1, 2: 2, 3: 1}


def test_exact_sets_tell_words_apart():
    texts = [b"a b c d", b"A b c", b"a", b"", b"b c d e a b c"]
    for width in (1, 2, 3):
        listed = [[x.lower() for x in t.split()] for t in texts]
        plain = [{tuple(w[k : k + width]) for k in range(max(1, len(w) - width + 1))} for w in listed]
        for s, p in zip(near_dedup.exact_sets(texts, width), plain, strict=True):
            for t, q in zip(near_dedup.exact_sets(texts, width), plain, strict=True):
                assert len(np.intersect1d(s, t)) <= len(p) == len(s)
        sets = near_dedup.exact_sets(texts, width)
        assert [[len(np.intersect1d(s, t)) for t in sets] for s in sets] == [[len(p & q) for q in plain] for p in plain]


def test_hot_keys_are_joined_by_broadcast(spark):
    from dictparse.llm.common import skewed_join

    left = spark.range(3000).selectExpr("id", "CASE WHEN id < 1000 THEN 7 WHEN id % 10 = 0 THEN NULL ELSE id END AS k")
    right = spark.range(0, 3000, 2).selectExpr("id AS k", "id * 2 AS v").unionByName(spark.createDataFrame([(7, 14)], "k long, v long"))
    plain = sorted(map(str, left.join(right, "k", "left").select("id", "k", "v").collect()))
    assert sorted(map(str, skewed_join(left, right, "k").select("id", "k", "v").collect())) == plain
    assert skewed_join(left, right, "k", how="inner").count() == left.join(right, "k").count()


def test_keep_first(spark, rows):
    docs = table(spark, rows).withColumn("own", F.lit(1)).withColumn("Rows", F.lit(2)).withColumn("kept", F.lit(3))
    kept = near_dedup.keep_first(docs)
    assert kept.columns == docs.columns
    expected = {i for i, _, c in brute_components(rows, 5) if i == c}
    assert sorted(r.doc_id if r.doc_id is not None else -1 for r in kept.collect()) == sorted(expected)


def test_sketch_estimates():
    rng = np.random.default_rng(3)
    for share in (0.5, 0.8, 0.95):
        pool = rng.integers(0, 1 << 63, 3000, dtype=np.uint64)
        k = int(2000 * share / (1 + share) * 1.0)
        a, b = pool[:1000], np.concatenate([pool[: int(2000 * share / (1 + share))], pool[1000 : 2000 - k + 0]])
        truth = len(np.intersect1d(a, b)) / len(np.union1d(a, b))
        ra, rb = near_dedup.registers(np.unique(a)), near_dedup.registers(np.unique(b))
        assert abs(near_dedup.likelihood_estimate(ra[None], rb[None], np.array([len(a)]), np.array([len(b)]))[0] - truth) < 0.15
        merged = near_dedup.registers(np.unique(np.concatenate([a, b])))
        assert (np.maximum(ra, rb) == merged).all()
