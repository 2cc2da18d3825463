"""The five stages, each on its own input, against what its operator decides by brute force."""

import random

import corpus_pipeline as P
from bundlegraph.llm import mixing


def test_stages(spark, tmp_path):
    rng = random.Random(1)
    vocab = {"en": ["".join(rng.choice("aeithnsr") for _ in range(rng.randint(2, 7))) for _ in range(200)], "de": ["".join(rng.choice("äuerschk") for _ in range(rng.randint(2, 7))) for _ in range(200)]}
    rows, labels = [], []
    for i in range(240):
        lang = "de" if i % 3 == 0 else "en"
        words = [rng.choice(vocab[lang]) for _ in range(rng.randint(30, 90))]
        if i % 6 == 1:
            words[5], words[20] = "xxidiotxx", "xxmoronxx"
        rows.append((i, " ".join(words), lang, f"src{i % 4}", 1))
        labels.append((i, 1, int(i % 6 == 1)))
    for k in range(20):  # near copies and copies
        words = rows[2 + 12 * k][1].split()
        words[-1] = "changed"
        rows.append((1000 + k, " ".join(words), "en", "src0", 1))
        rows.append((2000 + k, rows[2 + 12 * k][1], "en", "src1", 1))
    rows += [(3000, None, None, None, None), (3001, "12345 !!", "en", "src0", 1), (3002, "", "en", "src0", 1), (None, " ".join(vocab["en"][:50]), "en", None, 1)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long").selectExpr("*", "1 AS score", "2 AS rep")
    spark.createDataFrame(labels, "doc_id long, quality int, toxic int").write.parquet(str(tmp_path / "labels.parquet"))
    docs.select(*P.COLUMNS).write.parquet(str(tmp_path / "documents.parquet"))

    def step(k, df):
        out = P.STAGES[k][1](spark, df, str(tmp_path))
        out.write.parquet(str(tmp_path / f"s{k}"))
        return spark.read.parquet(str(tmp_path / f"s{k}"))

    known = step(0, docs)
    ids = lambda df: sorted(-1 if r.doc_id is None else r.doc_id for r in df.select("doc_id").collect())
    assert known.columns == P.COLUMNS
    assert ids(known) == sorted(-1 if r[0] is None else r[0] for r in rows if r[0] not in (3000, 3001, 3002))
    clean = step(1, known)
    assert ids(clean) == [i for i in ids(known) if i >= 240 or i == -1 or i % 6 != 1]
    one = step(2, clean)
    assert ids(one) == [i for i in ids(clean) if i < 1000 or i >= 3000]
    mixed = step(3, one)
    taken = {r.doc_id: r.taken // max(1, r.size) for r in mixing.mix_report(one).collect()}
    assert ids(mixed) == sorted(-1 if d is None else d for d, n in taken.items() for _ in range(n))
    packed = step(4, mixed)
    assert ids(packed.where("piece = 0")) == ids(mixed)
    assert packed.groupBy("sequence_id").sum("length").agg({"sum(length)": "max"}).first()[0] <= 4096
    assert P.run(spark, str(tmp_path)).count() == packed.count()
    empty = docs.limit(0)
    for _, stage in P.STAGES:
        assert stage(spark, empty, str(tmp_path)).count() == 0


def test_unlabelled_documents_with_letters_pass_the_first_stage(spark):
    rows = [(1, "some words here", None, "s", 1), (2, "12 !!", None, "s", 1), (3, None, None, "s", 1), (4, "wörter", None, "s", 1)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long")
    assert sorted(r.doc_id for r in P.keep_known_languages(spark, docs, "").collect()) == [1, 4]
