import zlib

import numpy as np
from pyspark.sql import functions as F

import corpus_pipeline
from pathsieve.llm import packing, shingle_dedup
from pathsieve.llm.tokens import encoder
from tests.conftest import DATA
from tests.llm.test_operators import _components, _cut, _print, _words


def test_pipeline_against_brute_force(spark):
    """Stages in plain Python; language ID is taken as it stands, since all documents have a language here."""
    docs = {r["doc_id"]: r["text"] for r in spark.read.parquet(f"{DATA}/documents.parquet").collect()}
    roots = _components({i: _print(t) for i, t in docs.items()}, 4)
    docs = {i: t for i, t in docs.items() if roots[i] == i}
    ids = sorted(docs)
    cuts = dict(zip(ids, _cut([docs[i] for i in ids]), strict=True))
    left = {}
    for i in ids:
        if not cuts[i][1]:
            left[i] = docs[i]
    items = [w for r in spark.read.parquet(f"{DATA}/benchmark.parquet").collect() if (w := _words(r["text"]))]
    windows = {tuple(w[k : k + 10]) for w in items for k in range(max(1, len(w) - 9))}
    hit = lambda t: any(tuple(w[k : k + n]) in windows for w in [_words(t)] for n in {len(x) for x in windows} for k in range(len(w) - n + 1))
    e = encoder(packing.VOCABULARY, False)
    expected = {}
    for i, t in left.items():
        if not hit(t):
            raw = e.encode([t])[0] + np.array([1], "<u4").tobytes()
            for k in range(0, len(raw), 4 * 4096):
                expected[i, k // (4 * 4096)] = (k // 4, len(raw[k : k + 4 * 4096]) // 4, zlib.crc32(raw[k : k + 4 * 4096]))
    found = {(r["doc_id"], r["piece"]): (r["start"], r["length"], r["ids_crc32"]) for r in corpus_pipeline.run(spark, DATA).collect()}
    assert {k: v for k, v in found.items() if k[0] in left} == expected  # documents that lost no bytes
    assert {k[0] for k in found} <= set(ids)


def test_stages_on_odd_and_empty_tables(spark, odd, nothing):
    columns = ["doc_id", "text", "lang", "source", "n_chars"]
    for table in (odd.select(columns), nothing.select(columns)):
        docs = table
        for k, (name, stage) in enumerate(corpus_pipeline.STAGES):
            path = f"{spark.conf.get('spark.checkpoint.dir')}/odd-{id(table)}-{k}"
            stage(spark, docs, DATA).write.parquet(path)
            docs = spark.read.parquet(path)
            assert k == 4 or docs.columns == columns, name


CLASHES = ["score", "lang_pred", "runs", "m", "mark", "id_of_row", "mark_of_row", "fingerprint", "words", "component_id", "hit_key", "key", "kept_id", "row", "length", "piece"]


def test_stages_keep_columns_of_any_name(spark, odd):
    columns = ["doc_id", "text", "lang", "source", "n_chars"]
    docs = odd.select(*columns, *[F.concat(F.lit(c), F.col("text")).alias(c) for c in CLASHES])
    plain = odd.select(columns)
    for name, stage in corpus_pipeline.STAGES[:-1]:
        found = stage(spark, docs, DATA)
        assert found.columns == docs.columns, name
        rows = found.collect()
        assert all(r[c] is None or r[c].startswith(c) for r in rows for c in CLASHES), name
        assert sorted(map(repr, (r["doc_id"] for r in rows))) == sorted(map(repr, (r["doc_id"] for r in stage(spark, plain, DATA).collect()))), name
    assert stage is corpus_pipeline.STAGES[-2][1] and corpus_pipeline.pack(spark, docs, DATA).count() >= odd.count()


def test_near_duplicates_are_those_of_similar_shingles(spark, odd):
    words = [f"w{k}" for k in range(200)]
    changed = lambda *at: " ".join("new" if k in at else w for k, w in enumerate(words))
    made = {1: changed(), 2: changed(20, 60, 100, 140), 3: changed(20, 60, 100, 140, 180, 40), 4: changed(10, 30, 50, 70, 90, 110), 5: " ".join(words[:100]), 6: "Short text", 7: "short  TEXT\n", 8: "short text too", None: changed(150)}
    made |= {100 + r["doc_id"]: r["text"] for r in spark.read.parquet(f"{DATA}/documents.parquet").collect()}
    split = {i: t.encode().lower().split() for i, t in made.items()}
    sets = {i: {tuple(w[k : k + 5]) for k in range(max(1, len(w) - 4))} for i, w in split.items()}
    root = {i: i for i in sets if i}

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    for a in root:
        for b in root:
            if a < b and 5 * len(sets[a] & sets[b]) >= 4 * len(sets[a] | sets[b]):
                x, y = find(a), find(b)
                root[max(x, y)] = min(x, y)
    expected = {i for i in root if find(i) == i}
    assert {1, 4, 5, 6, 8} <= expected and not {2, 3, 7} & expected and (_print(made[1]) ^ _print(made[2])).bit_count() > 4
    schema = "doc_id long, text string, lang string, source string, n_chars long"
    found = corpus_pipeline.near_duplicates(spark, spark.createDataFrame([(i, t, None, None, None) for i, t in made.items()], schema), DATA)
    assert sorted(r["doc_id"] for r in found.collect()) == sorted(expected)
    some = corpus_pipeline.near_duplicates(spark, odd, DATA)
    assert some.columns == odd.columns and {1, 3, 6, 8} <= {r["doc_id"] for r in some.collect()}


def test_language_stage_rejects_foreign_text_and_junk(spark):
    docs = spark.read.parquet(f"{DATA}/documents.parquet").select("doc_id", "text", "lang", "source", "n_chars")
    rng = np.random.default_rng(3)
    drawn = lambda letters, n: "".join(rng.choice(list(letters), n))
    others = ["Все люди рождаются свободными и равными в своем достоинстве и правах.", "人人生而自由，在尊严和权利上一律平等。", "Bütün insanlar hür, haysiyet ve haklar bakımından eşit doğarlar.", "Wszyscy ludzie rodzą się wolni i równi pod względem swej godności i swych praw."]
    others += [drawn("abcdefghijklmnopqrstuvwxyz ", 500), drawn("0123456789abcdef", 500), drawn("#$%&/()=?*+~x {}[]<>;:_", 500), "12 34", ""]
    more = spark.createDataFrame([(-1 - k, t, None, None, None) for k, t in enumerate(others)], docs.schema)
    found = [r["doc_id"] for r in corpus_pipeline.language_id(spark, docs.unionByName(more), DATA).select("doc_id").collect()]
    assert sorted(found) == sorted(r["doc_id"] for r in docs.select("doc_id").collect())


def test_one_text_of_a_component_stays_whatever_its_id(spark):
    base = [f"w{k}" for k in range(60)]
    near = [" ".join([*base[:59], last]) for last in ("x", "y", "z")]  # 55 of 57 shingles are common
    for ids in ((None, None, None), (7, 7, 7), (None, 7, 7)):
        rows = [*zip(ids, near, strict=True), (None, "another text without an id"), (7, "a text that shares the id and is like no other")]
        kept = shingle_dedup.one_of_each(spark.createDataFrame(rows, "doc_id long, text string")).collect()
        assert len(kept) == 3 and sum(r["text"] in near for r in kept) == 1, ids


def test_stage_keeps_the_rows_that_the_labels_of_near_duplicates_name(spark, odd, monkeypatch):
    labelled, operator = [], shingle_dedup.near_duplicates
    monkeypatch.setattr(shingle_dedup, "near_duplicates", lambda docs: labelled.append(operator(docs)) or labelled[-1])
    kept = sorted(repr(r["doc_id"]) for r in corpus_pipeline.near_duplicates(spark, odd, DATA).collect())
    rows = [r for found in labelled for r in found.collect()]
    assert len(labelled) == 1 and len(rows) == odd.count()  # every row is labelled
    named = {(r["component_id"], r["root_words"]) for r in rows}
    assert named <= {(r["doc_id"], r["words"]) for r in rows} and kept == sorted(repr(i) for i, _ in named)
