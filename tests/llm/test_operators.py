import hashlib
import math
import random
import re
import zlib
from collections import Counter

import duckdb
import numpy as np
import public_tokenizers
import pyarrow as pa
import pytest
import xxhash
from pyspark.sql import functions as F
from tokenizers import Tokenizer

from pathsieve.llm import components, decontamination, fingerprints, html_text, huffman, language, language_model, licenses, near_dedup, packing, queries, shingle_dedup, suffix_dedup
from pathsieve.llm.elias_fano import EliasFano, decoded
from pathsieve.llm.tokens import encoder
from tests.conftest import DATA


def rows(df):
    return [(r["doc_id"], r["text"]) for r in df.collect()]


def by_id(df):
    return {r["doc_id"]: r for r in df.collect()}


@pytest.fixture(scope="module")
def docs(spark):
    return spark.read.parquet(f"{DATA}/documents.parquet")


# -- 1 fingerprints ----------------------------------------------------------------------


def test_edited_fingerprints(spark, odd, nothing):
    found = fingerprints.edited_fingerprints(odd).collect()
    texts = sorted(((-1 if i is None else i, t or "") for i, t in rows(odd)), key=lambda x: (-x[0], x[1]))
    assert len(found) == len(texts)
    expected = Counter()
    for k, (i, t) in enumerate(texts):
        after = texts[(k + 1) % len(texts)][1]
        edited = t[: len(t) - len(t) // 2] + after[: len(t) // 2]
        expected[(i, len(t), hashlib.sha256(edited.encode()).hexdigest())] += 1
    assert Counter((-1 if r["doc_id"] is None else r["doc_id"], r["n_chars"], r["edited_sha256"]) for r in found) == expected
    prints = {r["doc_id"]: r["fingerprint"] for r in found}
    assert prints[1] == prints[2] and prints[3] == prints[4] == prints[5] == "0" * 32 and len(prints[6]) == 32
    assert all(0 <= r["near_edited"] <= 1 and 0 <= r["near_next"] <= 1 for r in found)
    assert fingerprints.edited_fingerprints(nothing).count() == 0


def test_votes_and_near_pairs(spark):
    texts = [(1, " ".join(f"w{k % 5}" for k in range(700))), (2, "a b"), (3, "a")]
    found = {r["id"]: (r["high"], r["low"]) for r in fingerprints.fingerprints(spark.createDataFrame(texts, "id long, text string"), ["id"]).collect()}
    for i, t in texts:
        w = t.split()
        terms = list(zip(w, w[1:], strict=False)) or [(w[0], None)]
        seed = lambda x, s=42: xxhash.xxh64_intdigest(x, s)
        votes = np.zeros(128, int)
        for a, b in terms:
            h = seed(a) if b is None else seed(b, seed(a))
            h0 = seed(int(h).to_bytes(8, "little"))
            votes += [(h >> k & 1) for k in range(64)] + [(h0 >> k & 1) for k in range(64)]
        bits = [int(2 * v > len(terms)) for v in votes]
        signed = lambda b: (x := sum(v << k for k, v in enumerate(b))) - (1 << 64 if x >> 63 else 0)
        assert found[i] == (signed(bits[:64]), signed(bits[64:])), i
    rng = random.Random(1)
    prints = [rng.getrandbits(128) for _ in range(30)]
    prints += [p ^ sum(1 << rng.randrange(128) for _ in range(rng.randrange(6))) for p in prints]
    half = lambda x: x - (1 << 64) if x >> 63 else x
    df = spark.createDataFrame([(half(p >> 64), half(p & (1 << 64) - 1)) for p in prints], "high long, low long")
    for radius in (1, 3, 4):
        expected = {frozenset((a, b)) for a in set(prints) for b in set(prints) if a != b and (a ^ b).bit_count() <= radius}
        got = [frozenset((((r["high"] % (1 << 64)) << 64) | r["low"] % (1 << 64), ((r["other_high"] % (1 << 64)) << 64) | r["other_low"] % (1 << 64))) for r in fingerprints.near_pairs(df, radius).collect()]
        assert set(got) == expected and len(got) == len(expected)


def test_near_fingerprints_are_counted(spark, docs):
    text = " ".join(f"word{k} and{k % 7}" for k in range(400))
    made = docs.select("doc_id", "text").unionByName(spark.createDataFrame([(-1, text), (-2, text), (-3, text + " more")], "doc_id long, text string"))
    found = by_id(fingerprints.edited_fingerprints(made))
    prints = {i: int(r["fingerprint"], 16) for i, r in found.items()}
    expected = {i: sum(0 < (p ^ q).bit_count() <= fingerprints.RADIUS for q in set(prints.values())) for i, p in prints.items()}
    assert {i: r["n_near"] for i, r in found.items()} == expected and found[-1]["n_near"] == found[-2]["n_near"] > 0


# -- 2 language --------------------------------------------------------------------------


def test_language(spark, docs, odd, nothing):
    found = queries.op2_kernel_language_id(spark, DATA).join(docs.select("doc_id", "lang"), "doc_id").where("held_out").collect()
    assert np.mean([r["lang"] == r["lang_pred"] for r in found]) > 0.95
    model = language.fit(docs)
    some = by_id(language.predict(odd, model))
    assert some[3]["lang_pred"] == some[4]["lang_pred"] == some[9]["lang_pred"] == "und" and some[3]["score"] == 0
    assert language.predict(odd, model).count() == odd.count()
    assert {r["lang_pred"] for r in language.predict(odd, language.fit(nothing)).collect()} == {"und"}
    assert language.accepted(odd, model, 0.0).columns == odd.columns
    assert all(r["held_out"] == (zlib.crc32(str(r["doc_id"]).encode()) % 5 == 0) for r in docs.select("doc_id", language.held_out(F.col("doc_id")).alias("held_out")).collect())


# -- 3 pages -----------------------------------------------------------------------------


def test_marked_article():
    page = html_text.parse(
        "<html><head><title>x</title><style>p{}</style></head><body><header><h1>Site</h1></header><nav><ul><li>Menu</ul></nav><script>var a='</p>'</script>"
        "<article><h1>Head &amp; tail</h1><p>One\n  two<br>three <b>four</b><p>Five&nbsp;six<div class='ad-slot ads'>Buy</div><aside>Side</aside><form><p>Name</p></form>"
        "<p class=notice>Cookies</p><!-- <p>no</p> --><ul><li>a<li>b</ul><table><tr><td>c<td>d</table></article><section id='comments'><p>First!</p></section><footer>&copy;</footer></body></html>"
    )
    assert html_text.main_text(page, [])[0] == "Head & tail\n\nOne two three four\n\nFive six\n\na\n\nb\n\nc\n\nd"


def test_plainest_mark_counts():
    page = html_text.parse("<body class='has-sidebar'><div id='main-wrap'><p>Crumbs</p><main><p>Above</p><article class='post'><p>Text<p>More</article></main><div class='content'><p>Else</p></div></div></body>")
    assert html_text.main_text(page, [])[0] == "Text\n\nMore"
    page = html_text.parse("<div class='top'>Hello</div><div class='entry-content'><p>Text</p><div class='related-posts'><p>Other</p></div></div>")
    assert html_text.main_text(page, [])[0] == "Text"
    assert html_text.main_text(html_text.parse("<p hidden>x<p>y<p style='display: none'>z</p>w"), [])[0] == "y\n\nw"
    assert html_text.main_text(html_text.parse("<article><p>a &lt;b&gt; 1 < 2 &amp;amp;</p><script>never ends"), [])[0] == "a <b> 1 < 2 &amp;"


def test_differencing_without_a_marked_article(spark):
    frame = lambda body: f"<body><p>Welcome to the site</p>{body}<p>Subscribe today</p></body>"
    pages = [(k, f"http://h.example/{'a' if k < 3 else 'b'}/{k}", frame(f"<p>Story {k} is long enough to be no copy</p><p>It ends {k}.</p>")) for k in range(6)]
    pages += [(10, "http://other.example/x", frame("<p>Alone</p>")), (11, None, None), (12, "http://h.example/z", ""), (12, "http://h.example/z", "")]
    df = spark.createDataFrame([(*p, "extra") for p in pages], "page_id long, url string, html string, key string")
    found = {}
    for r in html_text.extract(df).collect():
        found[r["page_id"]] = r["text"]
        assert r["n_chars"] == len(r["text"])
    assert found[4] == "Story 4 is long enough to be no copy\n\nIt ends 4." and found[11] == found[12] == ""
    assert found[10] == "Welcome to the site\n\nAlone\n\nSubscribe today"
    assert html_text.extract(df).count() == len(pages) and html_text.extract(df.limit(0)).count() == 0


def test_longest_common_subsequence(monkeypatch):
    rng = random.Random(3)
    for _ in range(200):
        a, b = ([rng.choice("abcd") for _ in range(rng.randrange(9))] for _ in range(2))
        table = [[0] * (len(b) + 1) for _ in range(len(a) + 1)]
        for i, x in enumerate(a):
            for j, y in enumerate(b):
                table[i + 1][j + 1] = table[i][j] + 1 if x == y else max(table[i][j + 1], table[i + 1][j])
        for many in (32, 0):  # 0: by rows of bits wherever lines are equal
            monkeypatch.setattr(html_text, "_MANY", many)
            got = html_text.common(a, b)
            assert len(got) == table[-1][-1] and got == sorted(set(got))


def _paired(pages):
    """Brute force: texts by page, neighbours looked for in the whole order, longest common subsequences by a table."""
    def lcs(a, b):
        table = [[[] for _ in range(len(b) + 1)] for _ in range(len(a) + 1)]
        for i, x in enumerate(a):
            for j, y in enumerate(b):
                table[i + 1][j + 1] = table[i][j] + [i] if x == y else max(table[i][j + 1], table[i + 1][j], key=len)
        return table[-1][-1]

    order = sorted(pages, key=lambda p: html_text._key(p[1], p[0]))
    parsed = [html_text.parse(p[2]) for p in order]
    host = [html_text.place(p[1])[0] for p in order]
    kept = [[x for x, d in zip(p.lines, p.dropped, strict=True) if not d] for p in parsed]
    near = lambda i, j: host[i] == host[j] and sum(len(parsed[j].lines[k]) for k in lcs(parsed[j].lines, parsed[i].lines) if not parsed[j].dropped[k]) > html_text.COPY * sum(map(len, kept[j]))
    out = {}
    for i, p in enumerate(order):
        a, b = i - 1, i + 1
        while a >= 0 and near(a, a + 1):
            a -= 1
        while b < len(order) and near(b - 1, b):
            b += 1
        gone = {k for j in (a, b) if 0 <= j < len(order) and host[j] == host[i] for k in lcs(parsed[i].lines, parsed[j].lines)}
        out[p[0]] = "\n\n".join(x for k, x in enumerate(parsed[i].lines) if k not in gone and not parsed[i].dropped[k])
    return out


def test_differencing_against_brute_force(spark):
    rng = random.Random(9)
    site, foot = [f"Site line {k}" for k in range(6)], [f"Foot line {k}" for k in range(6)]  # each once on a page: one alignment is longest
    pages = []
    for k in range(60):
        lines = [*site[: rng.randrange(3, 6)], *(f"Own words of page {k}, line {j}, long enough to be a story of its own" for j in range(rng.randrange(1, 4))), *foot[rng.randrange(2, 5) :]]
        if k % 10 in (4, 5):
            lines = [f"Own words of page {k - k % 10}, told again and again, long enough to be a story" for _ in range(8)] + foot[:2]  # copies side by side
        pages.append((k, f"http://h{k % 2}.example/{k % 7}/{k:02}", "<body>" + "".join(f"<p>{x}</p>" for x in lines) + "</body>"))
    found = {r["page_id"]: r["text"] for r in html_text.extract(spark.createDataFrame(pages, "page_id long, url string, html string")).collect()}
    assert found == _paired(pages)


def test_long_and_short_pages(spark):
    story = "".join(f"<p>Line {k} of a very long page &amp; more" for k in range(40_000))
    pages = [(1, "http://h/a", f"<article>{story}</article>"), (2, "http://h/b", "<p>same</p>" * 9000 + "<p>own" + " own" * 3000), (3, "http://h/c", "<p>same</p>" * 8000 + "<p>mine" + " mine" * 3000)]
    found = {r["page_id"]: r["text"] for r in html_text.extract(spark.createDataFrame(pages, "page_id long, url string, html string")).collect()}
    assert found[1].count("\n\n") == 39_999 and found[1].endswith("Line 39999 of a very long page & more") and found[3] == "mine" + " mine" * 3000


# -- 4 decontamination -------------------------------------------------------------------


def _words(text):
    return re.findall(r"[^\x00-\x2f\x3a-\x60\x7b-\x7f]+", re.sub("[A-Z]", lambda m: m[0].lower(), text or ""))


def test_contamination_against_brute_force(spark, odd, nothing, bench):
    found = decontamination.contamination(odd, bench).collect()
    assert len(found) == odd.count()
    items = {}
    for r in bench.collect():
        w = _words(r["text"])
        if w:
            items.setdefault("" if r["item_id"] is None else str(r["item_id"]), set()).update(tuple(w[k : k + 10]) for k in range(max(1, len(w) - 9)))
    expected = Counter()
    for i, text in rows(odd):
        w, hit, ids = _words(text), set(), set()
        for item, some in items.items():
            for x in some:
                for k in range(len(w) - len(x) + 1):
                    if tuple(w[k : k + len(x)]) == x:
                        hit.update(range(k, k + len(x)))
                        ids.add(item)
        expected[(i, len(w), len(hit), len(ids), hashlib.sha256(",".join(sorted(ids)).encode()).hexdigest(), bool(hit))] += 1
    assert Counter(map(tuple, found)) == expected
    assert decontamination.contamination(nothing, bench).count() == 0
    assert not any(r["contaminated"] for r in decontamination.contamination(odd, bench.limit(0)).collect())
    clean = decontamination.without_contaminated(odd, bench)
    assert clean.columns == odd.columns and clean.count() == sum(not r["contaminated"] for r in found)


def test_proximity(spark):
    docs = spark.createDataFrame([(1, "alpha x x beta"), (2, "beta alpha"), (3, "alpha x x x x x beta"), (4, "gamma")], "doc_id long, text string")
    phrases = spark.createDataFrame([("p", "alpha beta"), ("q", "gamma")], "item_id string, text string")
    found = {tuple(r) for r in decontamination.proximity_matches(docs, phrases, 3).collect()}
    assert found == {(1, "p", 0, 3), (2, "p", 0, 1), (4, "q", 0, 0)}


# -- 5 packing, 6 token files ------------------------------------------------------------


def test_chunks_give_the_tokenizers_ids(odd):
    rng = random.Random(5)
    texts = [t for _, t in rows(odd)] + ["".join(rng.choice("aB é.,'s1\n\t  <>ß中\x00") for _ in range(60)) for _ in range(300)] + ["a. B", "don't stop. it's", "<|endoftext|> x", " lead", "trail \n", "x.,  y"]
    texts += ["x <|endoftext|> y", "<|endoftext|>", "A<|ENDOFTEXT|>b", "<|startoftext|>one two<|endoftext|>", "<| endoftext |>"]
    for name, spaced in ((packing.VOCABULARY, False), (huffman.VOCABULARY, True)):
        e = encoder(name, spaced)
        fresh = Tokenizer.from_file(public_tokenizers.path(name))
        expected = [np.array(x.ids, "<u4").tobytes() for x in fresh.encode_batch([t or "" for t in texts], add_special_tokens=False)]
        assert e.encode(texts) == expected and e.encode(texts) == expected


def test_packing(spark, odd, nothing):
    found = packing.pack(packing.pieces(odd, capacity=512), 512).toPandas()
    e = encoder(packing.VOCABULARY, False)
    assert sum(found["length"]) == sum(len(x) // 4 + 1 for x in e.encode([t for _, t in rows(odd)]))
    for _, g in found.sort_values("offset").groupby("sequence_id"):
        assert g["offset"].tolist() == np.r_[0, np.cumsum(g["length"])[:-1]].tolist() and g["length"].sum() <= 512
    assert packing.pack(packing.pieces(nothing)).count() == 0


def test_plan_is_best_fit():
    rng = random.Random(2)
    for _ in range(30):
        lengths = [rng.randrange(1, 41) for _ in range(rng.randrange(1, 200))]
        slots = packing.plan(Counter(lengths), 40)
        bins, ranks = {}, Counter()
        for n in sorted(lengths, reverse=True):
            r = ranks[n]
            ranks[n] += 1
            s = next(s for s in slots if s[0] == n and s[1] <= r < s[2])
            at = s[5] + (r - s[1]) % s[3] * n
            key = s[4] + (r - s[1]) // s[3]
            assert bins.get(key, 0) == at and at + n <= 40
            bins[key] = at + n
        rooms = []  # one by one
        for n in sorted(lengths, reverse=True):
            fit = [k for k, room in enumerate(rooms) if room >= n]
            if fit:
                rooms[min(fit, key=rooms.__getitem__)] -= n
            else:
                rooms.append(40 - n)
        assert len(bins) == len(rooms)


def test_token_files_round_trip(spark, odd, nothing, tmp_path):
    huffman.write_tokens(odd, f"{tmp_path}/a")
    found = [tuple(r) for r in huffman.read_tokens(spark, f"{tmp_path}/a", with_ids=True).orderBy("start").collect()]
    texts = sorted(rows(odd), key=lambda x: (x[0] is not None, x[0] or 0, x[1] is not None, x[1] or ""))
    e, start = encoder(huffman.VOCABULARY, True), 0
    for (i, t), (doc, at, n, crc, ids) in zip(texts, found, strict=True):
        plain = np.frombuffer(e.encode([t])[0], "<u4").tolist() + [2]
        assert (i, start, len(plain), zlib.crc32(np.array(plain, "<u4").tobytes()), plain) == (doc, at, n, crc, ids)
        start += n
    huffman.write_tokens(nothing, f"{tmp_path}/b")
    assert huffman.read_tokens(spark, f"{tmp_path}/b").count() == 0


def test_codes():
    rng = np.random.default_rng(1)
    for n in (1, 2, 3, 50, 3000):
        counts = (rng.pareto(0.5, n) * 10).astype(np.int64) + 1
        counts[rng.random(n) < 0.2] = 0
        counts[0] = 1
        bits = huffman.code_lengths(counts)
        assert ((bits > 0) == (counts > 0)).all() and bits.max() <= huffman.LONGEST_CODE and sum(0.5 ** b for b in bits.astype(float) if b) <= 1
        ids = rng.choice(np.flatnonzero(counts), 5000).astype(np.uint32)
        book = huffman.Codebook(bits)
        payload, marks = book.encode(ids)
        assert (book.decode(payload, marks, len(ids)) == ids).all()
    assert huffman.code_lengths(np.array([1, 1, 2, 4, 8, 16, 32]), 3).tolist() == [3, 3, 3, 3, 3, 3, 2]


# -- 7 near duplicates -------------------------------------------------------------------


def _print(text):
    w = (text or "").encode().lower().split()
    shingles = [b" ".join(w[k : k + 4]) for k in range(len(w) - 3)] or ([b" ".join(w)] if w else [])
    votes = [sum(xxhash.xxh64_intdigest(s, 42) >> b & 1 for s in shingles) for b in range(64)]
    return sum(1 << b for b in range(64) if 2 * votes[b] > len(shingles))


def _components(prints, radius):
    root = {i: i for i in prints}

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    for a in prints:
        for b in prints:
            if a < b and (prints[a] ^ prints[b]).bit_count() <= radius:
                x, y = find(a), find(b)
                root[max(x, y)] = min(x, y)
    return {i: find(i) for i in prints}


def test_near_duplicates(spark, docs, odd, nothing):
    found = by_id(near_dedup.near_duplicates(docs))
    prints = {i: _print(t) for i, t in rows(docs)}
    assert {i: (int(r["fingerprint"], 16), r["component_id"]) for i, r in found.items()} == {i: (prints[i], c) for i, c in _components(prints, 4).items()}
    some = near_dedup.near_duplicates(odd).collect()
    assert len(some) == odd.count()
    ids = {r["doc_id"]: r["component_id"] for r in some}
    assert ids[1] == ids[2] == 1 and ids[3] == ids[4] == ids[5] == 3 and ids[7] in (1, 7)
    assert near_dedup.near_duplicates(nothing).count() == 0
    kept = near_dedup.one_of_each(odd)
    assert kept.columns == odd.columns and Counter(r["doc_id"] for r in kept.collect())[1] == 1
    a, b = "one two three four five six seven", "eight nine ten eleven twelve thirteen"
    for one_of_each in (near_dedup.one_of_each, shingle_dedup.one_of_each):
        some = spark.createDataFrame([(1, a), (7, a), (7, b), (None, b), (None, a + " more words here that differ from all others at length"), (None, a)], "doc_id long, text string")
        assert sorted((r["doc_id"] or 0, r["text"][:3]) for r in one_of_each(some).collect()) == [(0, "one"), (1, "one"), (7, "eig")]


def _edited(rng, base, most):
    out = list(base)
    for _ in range(rng.randrange(most + 1)):
        out[rng.randrange(len(out))] = f"edit{rng.randrange(10**6)}"
    return " ".join(out)


def test_shingle_links_against_brute_force(spark, monkeypatch):
    """A large group around one text, of which many are too far from it, and chains; one block or many."""
    rng = random.Random(11)
    bases = [[f"w{rng.randrange(500)}" for _ in range(n)] for n in (120, 120, 40)]
    texts = {i: _edited(rng, bases[i % 7 % 3], 5) for i in range(1, 240)}
    texts |= {300 + i: " ".join(f"c{k}" for k in range(4 * i, 4 * i + 60)) for i in range(25)}
    sets = {i: set(shingle_dedup.shingle_hashes(t)[1]) for i, t in texts.items()}
    root = {i: i for i in texts}
    for a in sorted(texts):
        for b in sorted(texts):
            if a < b and root[a] != root[b] and 5 * len(sets[a] & sets[b]) >= 4 * len(sets[a] | sets[b]):
                low, high = sorted((root[a], root[b]))
                root = {i: low if r == high else r for i, r in root.items()}
    docs = spark.createDataFrame(list(texts.items()), "doc_id long, text string")
    for members, size in ((shingle_dedup.MEMBERS, shingle_dedup.BYTES), (20, 1 << 22), (1024, 9000)):
        monkeypatch.setattr(shingle_dedup, "MEMBERS", members)
        monkeypatch.setattr(shingle_dedup, "BYTES", size)
        assert {r["doc_id"]: r["component_id"] for r in shingle_dedup.near_duplicates(docs).collect()} == root
    assert 1 < len(set(root.values())) < len(texts)


def test_a_meeting_gives_a_forest():
    rng = random.Random(5)
    base = [f"w{k}" for k in range(100)]
    sets = [np.unique(np.array(shingle_dedup.shingle_hashes(_edited(rng, base, 2))[1], np.uint64)).tobytes() for _ in range(200)]
    for own, i, j in (([0] * 200, 0, 0), ([k % 2 + 3 for k in range(200)], 3, 4)):
        rows = pa.table({"i": [i] * 200, "j": [j] * 200, "own": own, "words": list(range(200)), "component": list(range(200)), "shingles": sets})
        found = shingle_dedup._meeting(rows)
        assert 100 < found.num_rows < 200


def _near_prints(rng, seeds, copies):
    prints = [rng.getrandbits(64) for _ in range(seeds)]
    return sorted({*prints, *(p ^ sum(1 << k for k in rng.sample(range(64), rng.randrange(7))) for p in prints for _ in range(copies)), 0, 1, 15})


def test_tree_links_against_brute_force(monkeypatch):
    rng = random.Random(4)
    for leaf in (64, 3):
        monkeypatch.setattr(near_dedup, "LEAF", leaf)
        for seeds, copies in ((300, 1), (3, 120), (1, 300), (1, 0)):
            prints = _near_prints(rng, seeds, copies)
            tree = near_dedup.Tree(np.array(prints, np.uint64))
            tree.link(np.arange(len(prints)))
            expected = _components(dict(enumerate(prints)), 4)
            assert {k: tree._find(k) for k in expected} == expected and len(tree.forest) == len(prints) - len(set(expected.values()))
            half = len(prints) // 2
            tree = near_dedup.Tree(np.array(prints, np.uint64))
            tree.across(np.arange(half), np.arange(half, len(prints)))
            pairs = {(a, b) for a in range(half) for b in range(half, len(prints)) if (prints[a] ^ prints[b]).bit_count() <= 4}
            assert all(tree._find(a) == tree._find(b) for a, b in pairs) and len({x for e in tree.forest for x in e}) == len({x for e in pairs for x in e})


def test_links_in_branches_of_any_size(spark, monkeypatch):
    prints = _near_prints(random.Random(5), 40, 4)
    df = spark.createDataFrame([(p - (1 << 64) if p >> 63 else p,) for p in prints], "fingerprint long")
    expected = _components({p: p for p in prints}, 4)
    for large in (near_dedup.LARGE, 12):  # 12: branches are parted by shells, over and over
        monkeypatch.setattr(near_dedup, "LARGE", large)
        found = {r["fingerprint"] % (1 << 64): r["component"] for r in near_dedup.groups(df).collect()}
        first = {}
        assert found.keys() == expected.keys() and all(first.setdefault(expected[p], c) == c for p, c in found.items()) and len(set(found.values())) == len(set(expected.values()))
    assert near_dedup.blocks_for(1000) == 5 and near_dedup.blocks_for(10**9) > 5 and len(near_dedup.projections(6)) == 15


def test_components(spark):
    chain = [(k, k + 1) for k in range(20)] + [(30, 31), (31, 32), (32, 30), (40, 40)]
    found = {r["id"]: r["component"] for r in components.components(spark.createDataFrame(chain, "a long, b long"), "a", "b").collect()}
    assert found == dict.fromkeys(range(21), 0) | dict.fromkeys((30, 31, 32), 30)


# -- 8 repeated strings ------------------------------------------------------------------


def _cut(texts, n=200):
    raws = [(t or "").encode() for t in texts]
    seen = Counter(r[k : k + n] for r in raws for k in range(len(r) - n + 1))
    out = []
    for r in raws:
        gone = np.zeros(len(r) + 1, int)
        for k in range(len(r) - n + 1):
            if seen[r[k : k + n]] > 1:
                gone[k] += 1
                gone[k + n] -= 1
        covered = np.cumsum(gone)[:-1] > 0
        kept = bytes(np.frombuffer(r, np.uint8)[~covered])
        out.append((len(r), int(covered.sum()), int((np.diff(np.r_[0, covered.astype(int)]) == 1).sum()), hashlib.sha256(kept).hexdigest()))
    return out


@pytest.mark.parametrize("block", [suffix_dedup._BLOCK, 1])
def test_repeats_against_brute_force(spark, odd, nothing, monkeypatch, block):
    """block: 1 has every bucket of different spans cut to single windows."""
    monkeypatch.setattr(suffix_dedup, "_BLOCK", block)
    rng = random.Random(6)
    word = lambda: "".join(rng.choice("abcdeé") for _ in range(rng.randrange(2, 9)))
    shared = [" ".join(word() for _ in range(60)) for _ in range(4)]
    made = [" ".join(x for _ in range(rng.randrange(1, 5)) for x in (word(), rng.choice(shared)[rng.randrange(90) : rng.randrange(150, 330)], word())) for _ in range(60)]
    made += ["a" * 700, "ab" * 300, shared[0], shared[0][:200], shared[0][:199]]
    df = spark.createDataFrame(list(enumerate(made)), "doc_id long, text string")
    found = {r["doc_id"]: (r["n_bytes"], r["n_removed"], r["n_spans"], r["kept_sha256"]) for r in suffix_dedup.remove_repeats(df).collect()}
    assert found == dict(enumerate(_cut(made)))
    texts = rows(odd)
    expected = Counter((i, *x) for (i, _), x in zip(texts, _cut([t for _, t in texts]), strict=True))
    assert Counter((r["doc_id"], r["n_bytes"], r["n_removed"], r["n_spans"], r["kept_sha256"]) for r in suffix_dedup.remove_repeats(odd).collect()) == expected
    assert suffix_dedup.remove_repeats(nothing).count() == 0
    assert suffix_dedup.with_repeats_removed(odd).columns == odd.columns


def test_one_passage_in_many_contexts(spark, monkeypatch):
    """Contexts that agree with others for a few bytes, on either side of the passage: its bucket is cut in some places and sorted in others."""
    monkeypatch.setattr(suffix_dedup, "_BLOCK", 20_000)
    rng = random.Random(11)
    drawn = lambda n: "".join(rng.choice("xyz") for _ in range(n))
    passage = "".join(rng.choice("abcdefgh ") for _ in range(230))
    made = [drawn(220) + passage + drawn(220) for _ in range(250)]
    df = spark.createDataFrame([(k if k % 3 else None, t) for k, t in enumerate(made)], "doc_id long, text string")  # a third without an id
    found = Counter((r["n_removed"], r["n_spans"], r["kept_sha256"]) for r in suffix_dedup.remove_repeats(df).collect())
    expected = _cut(made)
    assert found == Counter(x[1:] for x in expected) and len({x[1] for x in expected}) > 4


def test_stretches_of_a_span():
    rng = random.Random(12)
    raw = rng.randbytes(300)
    for rel in (100, 168, 150):
        for width in (169, 43, 11, 3, 1):
            parts = list(suffix_dedup.stretches(raw, rel, width))
            assert [k for at, n, _ in parts for k in range(at, at + n)] == list(range(101))
            for at, n, common in parts:
                assert len({(rel - k) // width for k in range(at, at + n)}) == 1
                for k in range(at, at + n):
                    assert common in raw[k : k + 200]


def test_difference_cover():
    cover = suffix_dedup.difference_cover()
    assert {(a - b) % suffix_dedup.PERIOD for a in cover for b in cover} == set(range(suffix_dedup.PERIOD))


# -- 9 language model --------------------------------------------------------------------


def _check_scores(found, texts, train_ids):
    tokens = lambda t: (t or "").encode().translate(bytes.maketrans(bytes(range(65, 91)), bytes(range(97, 123)))).split() + [b"\n"]
    counts = Counter(w for i, t in texts if train_ids(i) for w in tokens(t))
    total, kinds = sum(counts.values()), len(counts)
    expected = sorted((str(i), len(tokens(t)), sum(counts[w] > 0 for w in tokens(t)), round(sum(math.log10((counts[w] + 1) / (total + kinds + 1)) for w in tokens(t)), 6)) for i, t in texts)
    assert sorted((str(r["doc_id"]), r["n_tokens"], r["n_known"], round(r["base_score"], 6)) for r in found) == expected


def _trigram_scores(texts, train_ids, kept):
    """log10 P of each text, with counts in dictionaries."""
    tokens = lambda t: [w.decode("utf-8") for w in (t or "").encode().translate(bytes.maketrans(bytes(range(65, 91)), bytes(range(97, 123)))).split()]
    c1, c2, c3 = Counter(), Counter(), Counter()
    for i, t in texts:
        if train_ids(i):
            w = [0, 1, *tokens(t), 2]  # starts and end
            c1.update(w)
            c2.update(zip(w, w[1:], strict=False))
            c3.update(zip(w, w[1:], w[2:], strict=False))
    total, kinds = sum(n for w, n in c1.items() if w not in (0, 1)), len(c1.keys() - {0, 1})
    out = []
    for _, t in texts:
        w, s = [0, 1, *tokens(t), 2], 0.0
        for u, v, x in zip(w, w[1:], w[2:], strict=False):
            p = (c1[x] + 1) / (total + kinds + 1)
            p = c2[v, x] / (c1[v] + kept) if c2[v, x] else kept / (c1[v] + kept) * p
            p = c3[u, v, x] / (c2[u, v] + kept) if c3[u, v, x] else kept / (c2[u, v] + kept) * p
            s += math.log10(p)
        out.append((s, len(w) - 2))
    return out


def _check_trigrams(found, texts, train_ids):
    expected = sorted((str(i), s, n) for (i, _), (s, n) in zip(texts, _trigram_scores(texts, train_ids, language_model.KEPT), strict=True))
    got = sorted((str(r["doc_id"]), r["score"], r["n_tokens"]) for r in found)
    for (i, s, n), (j, x, k) in zip(expected, got, strict=True):
        assert (i, n) == (j, k) and abs(s - x) < 3e-4 * n + 1e-6, (i, s, x, n)  # three codes of 16 bits


def test_scores(spark, docs, odd, nothing, monkeypatch):
    found = queries.op9_trie_lm_scoring(spark, DATA).collect()
    train_ids = lambda i: zlib.crc32(str(i).encode()) % 7 != 2
    _check_scores(found, rows(docs), train_ids)
    _check_trigrams(found, rows(docs), train_ids)
    held = [r for r in found if r["held_out"]]
    assert sum(r["score"] for r in held) > sum(r["base_score"] for r in held)
    # many shards and slices, few frequent tokens, hot pairs in several shards
    for name, value in (("MOST_FREQUENT", 40), ("SLICE", 30_000), ("SHARD", 20_000), ("HOT", 6), ("SALTS", 3)):
        monkeypatch.setattr(language_model, name, value)
    found = queries.op9_trie_lm_scoring(spark, DATA).collect()
    _check_scores(found, rows(docs), train_ids)
    _check_trigrams(found, rows(docs), train_ids)
    found = language_model.score(odd, F.col("doc_id") % 2 == 1).collect()
    odd_ids = lambda i: i is not None and i % 2 == 1
    _check_scores(found, rows(odd), odd_ids)
    _check_trigrams(found, rows(odd), odd_ids)
    none = language_model.score(odd, F.lit(False)).collect()
    assert len(none) == odd.count() and {r["train_tokens"] for r in none} == {0} and language_model.score(nothing, F.lit(True)).count() == 0


def test_elias_fano_and_trie():
    rng = np.random.default_rng(2)
    for n, universe in ((0, 10), (1, 1), (500, 100), (3000, 10**9), (3000, 1 << 62)):
        values = np.sort(rng.integers(0, universe, n))
        e = EliasFano.build(values, universe)
        assert (e.get(np.arange(n)) == values).all()
        if n:
            asked = np.r_[values, rng.integers(0, universe, 100)]
            at = e.find(asked, np.zeros(len(asked), np.int64), np.full(len(asked), n))
            assert all((values[a] == v) if a >= 0 else v not in values for a, v in zip(at, asked, strict=True))
    frequent = np.array([50, 40, 30, 20, 10])
    grams = rng.integers(0, 9, (400, 3))
    grams = np.where(grams < 5, grams + language_model.FIRST, language_model.RARE + grams * 7)
    u, v, w = grams.T
    none = (np.zeros(0, np.int64),) * 3
    shard = language_model.Shard(u, v, w, none, frequent, 3)
    asked = np.r_[grams, grams[:50, ::-1], np.full((1, 3), language_model.RARE + 1)]
    p3, p2, count = shard.answers(*asked.T)
    c3, c2, c1 = Counter(map(tuple, grams.tolist())), Counter(map(tuple, grams[:, :2].tolist())), Counter(grams[:, 0].tolist())
    for g, x, y, n in zip(asked.tolist(), p3, p2, count, strict=True):
        first = int(frequent[g[0] - language_model.FIRST]) if g[0] < language_model.RARE else c1[g[0]]
        pair, kept = c2[tuple(g[:2])], language_model.KEPT
        p = c3[tuple(g)] / (pair + kept) if c3[tuple(g)] else kept / (pair + kept)
        assert n == first and (x >= 0) == (tuple(g) in c3) and abs(decoded(np.int64(x if x >= 0 else -1 - x)) - math.log10(p)) < 1e-4
        p = pair / (first + kept) if pair else kept / (first + kept)
        assert (y >= 0) == (pair > 0) and abs(decoded(np.int64(y if y >= 0 else -1 - y)) - math.log10(min(p, 1))) < 1e-4


# -- 10 licenses -------------------------------------------------------------------------


def test_licenses(spark, odd, nothing):
    found = by_id(licenses.scan(odd))
    assert found[10]["base_labels"] == "cc-by,reserved" and found[10]["n_base"] == 2 and (found[10]["first_word"], found[10]["last_word"]) == (2, 6) and found[10]["score"] == 1.0
    assert found[3]["n_words"] == 0 and found[3]["first_word"] is None and found[3]["labels"] == "" and found[3]["score"] == 0
    assert licenses.scan(odd).count() == odd.count() and licenses.scan(nothing).count() == 0
    mit = spark.createDataFrame([(1, "x\nReleased UNDER the MIT license!\ny"), (2, "released under license")], "doc_id long, text string")
    assert {i: (r["labels"], r["n_base"]) for i, r in by_id(licenses.scan(mit)).items()} == {1: ("mit", 0), 2: ("", 0)}
    assert licenses.scan(mit, templates={}).count() == 2
    text = "Creative Commons attribution international work: Released under the MIT License"
    for times in (1, 2, 3):  # repeated rows
        found = licenses.scan(spark.createDataFrame([(1, text)] * times, "doc_id long, text string")).collect()
        assert [(r["labels"], r["score"]) for r in found] == [("mit", 1.0)] * times
    notice = licenses.TEMPLATES["mit-permission"].split()
    wrapped = "\n".join(" ".join(notice[k : k + 7]) for k in range(0, len(notice), 7))
    found = by_id(licenses.scan(spark.createDataFrame([(1, f"x\n\n{wrapped}\n\ny"), (2, wrapped.replace("\n", "\n\n")), (3, wrapped.replace("\n", "\n" + "z " * 80 + "\n"))], "doc_id long, text string")))
    assert {i: r["labels"] for i, r in found.items()} == {1: "mit-permission", 2: "", 3: ""}


def test_similar_blocks_against_brute_force(spark):
    rng = random.Random(8)
    vocabulary = [f"w{k}" for k in range(12)]
    templates = {f"t{k}": " ".join(rng.sample(vocabulary, rng.randrange(1, 8))) for k in range(6)}
    lines = [" ".join(rng.choice(vocabulary) for _ in range(rng.randrange(1, 15))) for _ in range(150)]
    texts = {str(k): "\n".join(lines[k : k + 6]) for k in range(0, 150, 6)}
    texts["6"] = texts["6"].replace("\n", "\n\n")
    df = spark.createDataFrame(list(texts.items()) * 2, "key string, text string")  # repeated rows
    got = {(r["key"], r["label"], round(r["containment"], 9)) for r in licenses.similar_blocks(df, templates, 0.75).collect()}
    expected = set()
    for key, text in texts.items():
        split = text.split("\n")
        some = [" ".join(split[a:b]) for a in range(len(split)) for b in range(a + 1, min(len(split), a + licenses.WRAPPED) + 1) if b == a + 1 or all(split[a:b])]
        for x in some:
            expected |= {(key, t, c) for t, y in templates.items() if (c := len(set(y.split()) & set(x.split())) / len(set(y.split()))) >= 0.75}
    best = lambda rows: {(k, t): max(c for a, b, c in rows if (a, b) == (k, t)) for k, t, _ in rows}
    assert {k: round(v, 9) for k, v in best(expected).items()} == best(got)


@pytest.mark.parametrize("name", ["op4_positional_decontamination", "op10_license_scan"])
def test_queries_equal_their_sql(spark, name):
    con = duckdb.connect()
    for t in ("documents", "benchmark"):
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{DATA}/{t}.parquet'")
    df = queries.queries()[name](spark, DATA)
    columns = sorted(df.columns)
    cursor = con.execute(queries.oracle_sql()[name])
    at = [[d[0] for d in cursor.description].index(c) for c in columns]
    assert sorted(repr(tuple(r[c] for c in columns)) for r in df.collect()) == sorted(repr(tuple(r[k] for k in at)) for r in cursor.fetchall())
