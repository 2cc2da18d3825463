"""Small tests of the training-data operators: hard inputs, brute force, round trips, held-out accuracy."""

import hashlib
import itertools
import random
import zlib

import numpy as np
import pytest
from pyspark.sql import functions as F

from bundlegraph.llm import chat, langid, media, mixing, near_dup, packing, sharding, toxicity
from bundlegraph.llm.bpe import ChunkEncoder, vocabulary

WORD_BPE = vocabulary("word_bpe_49k.json")
DOCS = "doc_id long, text string, lang string, source string, n_chars long"


def documents(spark, rows):
    """Rows of documents plus columns whose names clash with the operators' own."""
    df = spark.createDataFrame([(d, t, lang, s, None) for d, t, lang, s in rows], DOCS)
    return df.selectExpr("*", "1 AS part", "2 AS size", "3 AS n", "4 AS rep", "5 AS score", "6 AS __copy", "'x' AS key")


ODD = [(1, "a b c d e", "en", "s"), (1, "a b c d e", "en", "s"), (2, None, None, None), (3, "", "en", "t"), (None, "null id here now", "en", None), (4, " \n\t ", "de", "s"), (5, "word " * 30000, "en", "hot")]


# --- packing ---------------------------------------------------------------------------------------


def test_plan_is_valid_and_meets_known_optima():
    rng = random.Random(3)
    for _ in range(150):
        cap = rng.choice([10, 24, 60])
        counts = np.zeros(cap + 1, dtype=np.int64)
        for _ in range(rng.randint(1, 14)):
            counts[rng.randint(1, cap)] += rng.randint(1, 6)
        plan = packing.plan(counts, cap).patterns
        back = np.zeros_like(counts)
        for pattern, n in plan.items():
            assert n > 0 and sum(s * k for s, k in pattern) <= cap
            for s, k in pattern:
                back[s] += n * k
        assert (back == counts).all()
        assert packing.lower_bound(counts, cap) <= sum(plan.values()) <= sum(packing.best_fit_decreasing(counts, cap).values())


def fewest_bins(items, cap):
    """Exhaustive search."""
    items, best = sorted(items, reverse=True), len(items)

    def go(i, room):
        nonlocal best
        if len(room) >= best:
            return
        if i == len(items):
            best = len(room)
            return
        for k in {r: k for k, r in enumerate(room) if r >= items[i]}.values():
            go(i + 1, [*room[:k], room[k] - items[i], *room[k + 1 :]])
        go(i + 1, [*room, cap - items[i]])

    go(0, [])
    return best


def test_search_finds_the_optimum():
    rng, better = random.Random(11), 0
    for _ in range(300):
        cap = rng.choice([20, 30, 50])
        items = [rng.randint(2, cap * 2 // 3) for _ in range(rng.randint(3, 11))]
        counts = np.bincount(items, minlength=cap + 1)
        plan = packing.plan(counts, cap)
        assert plan.proven and plan.bins == sum(plan.patterns.values()) == fewest_bins(items, cap)
        better += plan.bins < sum(packing.best_fit_decreasing(counts, cap).values())
    assert better > 0


def test_search_beats_best_fit_at_the_query_capacity():
    for lo, hi, n in ((300, 1400, 1000), (700, 1400, 500)):
        counts = np.bincount(np.random.default_rng(0).integers(lo, hi, n), minlength=4097)
        plan = packing.plan(counts, 4096)
        assert plan.bins < sum(packing.best_fit_decreasing(counts, 4096).values()) and plan.least <= plan.bins
    stopped = packing.plan(counts, 4096, search_nodes=0)
    assert not stopped.proven and sum(stopped.patterns.values()) == stopped.bins


def test_undominated_fillings_equal_brute_force():
    rng = random.Random(3)
    for _ in range(60):
        room, stock = rng.randint(6, 14), [rng.randint(1, 9) for _ in range(rng.randint(2, 6))]
        left = np.bincount(stock, minlength=room + 1)
        got = [c for c in packing.completions(left, room, room) if c is not None]
        want = set()
        for r in range(len(stock) + 1):
            for pick in itertools.combinations(sorted(stock, reverse=True), r):
                if sum(pick) > room:
                    continue
                rest = list(stock)
                for x in pick:
                    rest.remove(x)
                waste = room - sum(pick)
                parts = [p for k in range(len(pick) + 1) for p in itertools.combinations(pick, k)]
                if not any(sum(p) < x <= sum(p) + waste or (x == sum(p) and len(p) > 1) for x in rest for p in parts):
                    want.add(pick)
        assert sorted(tuple(s for s, n in items for _ in range(n)) for items, _ in got) == sorted(want)
        assert [w for _, w in got] == sorted(w for _, w in got)


def test_pack_documents(spark):
    got = packing.pack(documents(spark, ODD), WORD_BPE, capacity=64).toPandas()
    enc, want = ChunkEncoder(WORD_BPE), []
    for d, t, *_ in ODD:
        ids = np.array([*np.frombuffer(enc.encode([t])[0], "<u4"), 1], "<u4")
        want += [(d, k // 64, k, min(64, len(ids) - k), zlib.crc32(ids[k : k + 64].tobytes())) for k in range(0, len(ids), 64)]
    key = lambda r: tuple(-1 if x is None or x != x else int(x) for x in r)
    assert sorted(map(key, got[["doc_id", "piece", "start", "length", "ids_crc32"]].itertuples(index=False))) == sorted(map(key, want))
    for _, g in got.sort_values("offset").groupby("sequence_id"):
        assert (g["offset"] == g["length"].cumsum() - g["length"]).all() and g["length"].sum() <= 64
    assert got["sequence_id"].nunique() == -(-got["length"].sum() // 64)
    assert packing.pack(documents(spark, ODD).limit(0), WORD_BPE).count() == 0


# --- sharding --------------------------------------------------------------------------------------


def test_byte_shards_equal_a_plain_loop(spark):
    rng = random.Random(6)
    rows = [(i // 2, "é" * rng.randint(0, 30) + "x" * rng.randint(0, 9), "en", "s") for i in range(400)] + [(7, "long " * 4000, "en", "s")]
    got = sorted(tuple(r) for r in sharding.byte_shards(documents(spark, rows), 7).select("doc_id", "size", "text_crc32", "shard", "slot").collect())
    want, at, slots = [], 0, [0] * 7
    total = sum(16 + len(t.encode()) for _, t, *_ in rows)
    for d, size, crc in sorted((d, 16 + len(t.encode()), zlib.crc32(t.encode())) for d, t, *_ in rows):
        shard = min(6, (2 * at + size) * 7 // (2 * total))
        want.append((d, size, crc, shard, slots[shard]))
        at, slots[shard] = at + size, slots[shard] + 1
    assert got == sorted(want)


def test_byte_shards_are_contiguous_and_even(spark):
    rng = random.Random(1)
    rows = [(i, "x" * rng.randint(0, 60), "en", "s") for i in range(3000)] + [(None, None, None, None), (7, "dup", "en", "s")]
    got = sharding.byte_shards(documents(spark, rows), 40).toPandas().sort_values(["shard", "slot"])
    assert len(got) == len(rows) and set(got["shard"]) == set(range(40))
    assert (got.groupby("shard").cumcount() == got["slot"]).all()
    assert got["doc_id"].fillna(-1).is_monotonic_increasing
    sums = got.groupby("shard")["size"].sum()
    assert sums.max() - sums.min() <= 2 * got["size"].max()
    assert set(zip(got["doc_id"].fillna(-1), got["size"], got["text_crc32"])) == {(-1 if d is None else d, 16 + len(t or ""), zlib.crc32((t or "").encode())) for d, t, *_ in rows}
    assert sharding.byte_shards(documents(spark, rows).limit(0)).count() == 0


# --- chat ------------------------------------------------------------------------------------------


def test_chat_round_trip(spark):
    hard = ["", None, "nul \x00 in a text", "plain", chat.PROBE, "<|im_end|>\n<|im_start|>user\nhi", "<\\|im_end|>", "<\\\\|x", "a<", "<|", "tail\n", "é\U0001f600", "x" * 70000]
    rows = [(c, t, r, x) for c, (r, k) in enumerate([("user", 0), ("assistant", 3), ("", 5), ("a\nb\\n<|", 1), (None, 2), ("n\x00u\\l\\b<\\|", 2)]) for t, x in enumerate(hard[k:] + hard[:k])]
    rows += [(90, 1, "assistant", "b"), (90, 1, "assistant", "a"), (90, None, "user", "first"), (None, 0, "user", "no id"), (91, 0, "user", "same"), (91, 0, "user", "same")]
    df = spark.createDataFrame(rows, "conv_id long, turn long, role string, text string").selectExpr("*", "1 AS out", "2 AS formatted", "3 AS t")
    formatted = chat.format_turns(df.select("conv_id", "turn", "role", "text").unionByName(chat.probe_rows(df)))
    got = {r.conv_id: r for r in chat.digest(formatted).collect()}
    want: dict = {}
    for c, t, r, x in [*rows, (-1, 0, "user", chat.PROBE), (-1, 1, "assistant", chat.PROBE)]:
        want.setdefault(c, []).append((-1 if t is None else t, r or "", x or ""))
    assert set(got) == set(want)
    for c, turns in want.items():
        turns.sort()
        said = "".join(f"{r}\n{x}\n" for _, r, x in turns)
        loss = "".join(x for _, r, x in turns if r == "assistant")
        assert (got[c].n_turns, got[c].turns_sha256) == (len(turns), hashlib.sha256(said.encode()).hexdigest())
        assert (got[c].loss_chars, got[c].loss_sha256) == (len(loss), hashlib.sha256(loss.encode()).hexdigest())
    text = {r.conv_id: r.formatted for r in formatted.collect()}
    assert "<|im_end|>\n" in text[0] and all(got[c].formatted_chars == len(text[c]) for c in text)
    assert chat.format_turns(df.limit(0)).count() == 0


# --- media -----------------------------------------------------------------------------------------


@pytest.mark.parametrize("compression", [media.PLAIN, media.LZW, media.DEFLATE, media.PACKBITS])
@pytest.mark.parametrize("tile", [None, (16, 32)])
def test_tiff_variants_round_trip(compression, tile):
    rng = np.random.default_rng(compression)
    for order in "<>":
        for predictor in (False, True):
            pages = [rng.integers(0, 256, (h, w)).astype(np.uint8) for h, w in ((1, 64), (37, 50))] + [np.repeat(rng.integers(0, 4, (90, 8)), 9, axis=1).astype(np.uint8)]
            data = media.encode_tiff(pages, compression, predictor, tile, strip_rows=11, order=order)
            back = list(media.decode_tiff(data))
            assert len(back) == 3 and all((a == b).all() for a, b in zip(pages, back))


def test_codecs():
    rng = random.Random(4)
    for size in (0, 1, 2, 127, 128, 129, 5000, 70000):
        for alphabet in (1, 2, 256):
            data = bytes(rng.randrange(alphabet) for _ in range(size))
            assert media.packbits_decode(media.packbits_encode(data), size) == data
            assert media.lzw_decode(media.lzw_encode(data), size) == data
    # fixed value: the example of the PackBits note
    assert media.packbits_decode(bytes.fromhex("feaa0280002afdaa0380002a22f7aa"), 24).hex() == "aaaaaa80002aaaaaaaaa80002a22aaaaaaaaaaaaaaaaaaaa"


def test_text_media(spark):
    rows = [(d, t, lang, s) for d, t, lang, s in ODD] + [(9, "é" * 32, "fr", "s"), (10, "a b c d e", "en", "z")]
    got = media.text_media(documents(spark, rows)).collect()
    assert len(got) == len(rows)
    for r, t in ((r, t) for r in got for d, t, *_ in rows if d == r.doc_id):
        raw = (t or "").encode()
        full = raw + b"\0" * (-len(raw) % 64 if raw else 64)
        assert (r.n_bytes, r.payload_bytes, r.payload_sha256, r.tail_crc32) == (len(raw), len(full), hashlib.sha256(full).hexdigest(), zlib.crc32(full[-64:]))
    assert len({(r.media_sha256, r.feature) for r in got if r.doc_id in (1, 10)}) == 1
    pages = media.tiff_pages(media.texts_as_tiff(documents(spark, rows)), "doc_id", "media")
    picks = {media.text_to_tiff(bytes([k] * 64))[:2] for k in range(200)}
    assert picks == {b"II", b"MM"}
    for k in range(300):
        payload = bytes([k % 256, k // 256] * 96 * (1 + k % 3))
        assert b"".join(p.tobytes() for p in media.decode_tiff(media.text_to_tiff(payload))) == payload
    assert pages.where("doc_id = 5").count() == -(-(-(-150000 // 64)) // media.PAGE_H)
    bad = spark.createDataFrame([(1, b"II junk"), (2, None)], "doc_id long, media binary")
    assert [(r.doc_id, r.page) for r in media.tiff_pages(bad, "doc_id", "media", keep_bad=True).collect()] == [(1, -1)]


# --- mixing ----------------------------------------------------------------------------------------


def test_mix_meets_targets(spark):
    rng = random.Random(8)
    rows = [(i, "w " * rng.randint(0, 40), "en", rng.choice(["a", "b", "c", "d", None, "hot", "hot", "hot"])) for i in range(4000)] + [(None, "x y", "en", "a"), (3, None, None, None)]
    got = mixing.mix_report(documents(spark, rows)).toPandas()
    source = {d: s for d, _, _, s in rows[:4000]}
    got = got[got["doc_id"].notna() & (got["doc_id"] != 3)]
    got["source"] = [source[int(d)] or "~" for d in got["doc_id"]]
    sums = got.groupby("source").agg(taken=("taken", "sum"), target=("target", "first"), size=("source_size", "first"))
    assert (abs(sums["taken"] - sums["target"]) <= 160).all()
    assert (got["taken"] <= 2 * got["size"]).all()
    total, names = sums["size"].sum(), ["a", "b", "c", "d", "hot", "~"]
    w = dict(zip(names, [3, 1, 2, 3, 1, 2]))
    want, open_, left = {}, set(names), 1.5 * total
    while open_:  # the plain loop: share, stop at the cap, share the rest again
        part = {s: left * w[s] / sum(w[k] for k in open_) for s in open_}
        over = {s for s in open_ if part[s] > 2 * sums["size"][s]}
        if not over:
            want |= part
            break
        for s in over:
            want[s] = 2.0 * sums["size"][s]
            left -= want[s]
        open_ -= over
    assert all(abs(want[s] - sums["target"][s]) < 1e-6 for s in names)
    assert mixing.mix_report(documents(spark, rows).limit(0)).count() == 0


def test_mix_emits_rows_as_often_as_the_report_says(spark):
    docs = documents(spark, [(i, "w " * (i % 9), "en", "ab"[i % 2]) for i in range(300)]).cache()
    out = mixing.mix(docs)
    assert out.columns == docs.columns
    times = {r.doc_id: r["count"] for r in out.groupBy("doc_id").count().collect()}
    report = mixing.mix_report(docs).collect()
    assert max(times.values()) <= 2
    assert sum(r.taken for r in report) == sum((d % 9) * n for d, n in times.items())


# --- language ID and toxicity ------------------------------------------------------------------------


def test_words_first_then_shorter_ngrams(spark):
    rng = random.Random(2)
    en, de = ["the", "thing", "with", "other", "than"], ["der", "schon", "nicht", "schule", "machen"]
    rows = [(i, " ".join(rng.choice(v) for _ in range(20)), lang, "s") for i, (v, lang) in enumerate([(en, "en"), (de, "de")] * 60)]
    rows += [(1001, "schulen machte nichtig", "de", "s"), (1002, "withing thethan", "en", "s"), (1003, "123 !!", "en", "s"), (1004, None, "de", "s"), (1005, "", None, "s"), (None, "the thing", "en", "s"), (1006, "the " * 50000, None, "s")]
    docs = documents(spark, rows)
    got = {r.doc_id: r for r in langid.language_report(docs).collect()}
    assert len(got) == len({r[0] for r in rows})
    assert (got[1001].lang_pred, got[1002].lang_pred, got[1006].lang_pred) == ("de", "en", "en")
    assert all((got[d].lang_pred, got[d].score) == ("und", 0.0) for d in (1003, 1004, 1005))
    assert all(r.held_out == (r.doc_id is not None and zlib.crc32(str(r.doc_id).encode()) % 3 == 1) for r in got.values())
    assert all(r.lang_pred == lang for d, _, lang, _ in rows[:120] for r in [got[d]])
    assert {r.lang_pred for r in langid.language_report(docs.withColumn("lang", F.lit(None).cast("string"))).collect()} == {"und"}
    assert langid.language_report(docs.limit(0)).count() == 0


def test_scores_equal_a_plain_dictionary_loop(spark):
    rng = random.Random(12)
    en, de = ["the", "thing", "with", "other", "than"], ["der", "schon", "nicht", "schule", "machen"]
    rows = [(i, " ".join(rng.choice(v) for _ in range(12)), lang, "s") for i, (v, lang) in enumerate([(en, "en"), (de, "de")] * 20)]
    model = langid.fit_languages(documents(spark, rows))
    odd = ["schulen und withing", "The THING", "x", "nichtothe " * 60, "der the"]
    docs = documents(spark, [(i, t, None, "s") for i, t in enumerate(odd)])
    for r in langid.predict_languages(docs, model).collect():
        found = "".join(c if c.isalpha() else " " for c in odd[r.doc_id].lower()).split()
        total = {lang: 0.0 for lang in model.langs}
        for w in found:
            if w in model.words:
                vec = model.words[w]
            else:  # longest known pieces from left to right
                text, vec, pieces = f" {w} ", 0.0, 0
                while text:
                    n = next((n for n in (4, 3, 2, 1) if len(text) >= n and text[:n] in model.parts), None)
                    if n is None:
                        text = text[1:]
                        continue
                    vec, pieces, text = vec + model.parts[text[:n]], pieces + 1, text[n:]
                vec = vec / max(1, pieces)
            for k, lang in enumerate(model.langs):
                total[lang] += float(vec[k])
        z = {lang: t / len(found) * min(len(found), 40) for lang, t in total.items()}
        best = max(sorted(z), key=z.get)
        share = np.exp(z[best] - max(z.values())) / sum(np.exp(v - max(z.values())) for v in z.values())
        assert r.lang_pred == best and abs(r.score - share) < 1e-4


def test_rare_languages_and_rare_words_are_learned(spark):
    """A language of one document beside a large one, and a sample whose words occur once each."""
    rng = random.Random(6)
    word = lambda letters: "".join(rng.choice(letters) for _ in range(rng.randint(3, 6)))
    en = [word("aeithnsr") for _ in range(150)]
    rows = [(i, " ".join(rng.choice(en) for _ in range(40)), "en", "s") for i in range(400)]
    rows += [(1000, " ".join(word("кмноптя") for _ in range(12)), "ru", "s"), (1001, " ".join(word("кмноптя") for _ in range(12)), None, "s")]
    model = langid.fit_languages(documents(spark, rows), train_docs=50)
    assert model.langs == ["en", "ru"]
    got = {r.doc_id: r.lang_pred for r in langid.predict_languages(documents(spark, rows), model).collect()}
    assert got == {d: "ru" if d >= 1000 else "en" for d, *_ in rows}
    once = [(0, "thing with other", "en", "s"), (1, "schon nicht machen", "de", "s"), (2, "withing", None, "s"), (3, "nichtig", None, "s"), (4, "12", "en", "s")]
    model = langid.fit_languages(documents(spark, once))
    got = {r.doc_id: r.lang_pred for r in langid.predict_languages(documents(spark, once), model).collect()}
    assert got == {0: "en", 1: "de", 2: "en", 3: "de", 4: "und"}


def test_gradients_match_differences():
    rng = np.random.default_rng(0)
    net = toxicity.Network()
    net.p = {k: v.astype(np.float64) + rng.normal(size=v.shape) * 0.1 for k, v in net.p.items()}
    x, mask = rng.normal(size=(5, 7, toxicity.INPUTS)), np.arange(7) < np.array([7, 3, 5, 1, 7])[:, None]
    y, w = np.array([1, 0, 1, 0, 1.0]), np.ones(5)
    grads = net.gradients(x, mask, y, w)[1]
    for k, v in net.p.items():
        i = tuple(rng.integers(0, s) for s in v.shape)
        old = v[i]
        v[i] = old + 1e-5
        up = net.gradients(x, mask, y, w)[0]
        v[i] = old - 1e-5
        down = net.gradients(x, mask, y, w)[0]
        v[i] = old
        assert abs((up - down) / 2e-5 - grads[k][i]) < 1e-6


def test_embedding_gradients_match_differences():
    rng = np.random.default_rng(1)
    net = toxicity.Network()
    inputs = toxicity.Inputs({"bad": 1.0}, {"^bad": 0.5})
    tokens = toxicity.Tokens()
    assert [tokens.add(inputs, t) for t in ("Bad", "words", "here", "x")] == [1, 2, 3, 4]
    tokens.done()
    ids, mask, y, w = rng.integers(1, 5, (3, 6)), np.ones((3, 6), dtype=bool), np.array([1, 0, 1.0], dtype=np.float32), np.ones(3, dtype=np.float32)
    types, where = np.unique(ids, return_inverse=True)
    where = where.reshape(ids.shape)
    loss = lambda: net.gradients(net.inputs(tokens, types)[where], mask, y, w)
    _, _, din = loss()
    dx = np.zeros((len(types), toxicity.INPUTS), dtype=np.float32)
    np.add.at(dx, where, din)
    grads = net.embedding_gradients(tokens, types, dx)
    for kind, row in (("word", tokens.word[types[0]]), ("gram", tokens.gram_rows(types[:1])[0][0])):
        old = net.e[kind][row, 3]
        net.e[kind][row, 3] = old + 0.05
        up = loss()[0]
        net.e[kind][row, 3] = old - 0.05
        down = loss()[0]
        net.e[kind][row, 3] = old
        assert abs((up - down) / 0.1 - grads[kind][row, 3]) < 2e-3 * max(1.0, abs(grads[kind][row, 3]))


def test_token_inputs_in_bulk_match_the_plain_rule():
    """Six figures, embedding rows and n-grams of many tokens at once, against each token by itself."""
    rng = random.Random(8)
    letters = "abcxyzßéñAÉ0'-^$.,\x00\u0130\u4e2d\U0001f600\ud800"
    tokens = ["", "a", "ab", "--", "^x$", "a$^b", "\x00\x00\x00", "ab\x00", "Straße,", *("".join(rng.choices(letters, k=rng.randint(1, 12))) for _ in range(3000)), "é" * 5000]
    tokens = [t for t in dict.fromkeys(tokens) if t]
    bare = [t.lower().strip(toxicity._EDGE) for t in tokens]
    every = sorted({g for w in bare for g in toxicity.Inputs.parts(w)})
    inputs = toxicity.Inputs({w: rng.uniform(-2, 2) for w in rng.sample(bare, 500)}, {g: rng.uniform(-2, 2) for g in rng.sample(every, len(every) // 2)})
    figures, words, many, rows = inputs.of(tokens)
    at = 0
    for i, (t, w) in enumerate(zip(tokens, bare)):
        parts = toxicity.Inputs.parts(w)
        got, known = [inputs.grams.get(g, 0.0) for g in parts] or [0.0], inputs.words.get(w)
        want = ((known or 0.0) / 2, known is not None, min(len(w), 20) / 10, max(got) / 2, sum(got) / len(got), sum(c.isupper() for c in t) / len(t))
        assert np.allclose(figures[i], want, atol=1e-6), t
        assert words[i] == zlib.crc32(w.encode("utf-8", "surrogatepass")) % toxicity.WORD_ROWS and many[i] == len(parts)
        assert rows[at : at + many[i]].tolist() == [zlib.crc32(g.encode("utf-8", "surrogatepass")) % toxicity.GRAM_ROWS for g in parts]
        at += many[i]
    assert at == len(rows)
    assert [len(x) for x in inputs.of([])] == [0, 0, 0, 0] and toxicity.Inputs({}, {}).of(["word"])[0][0, 3:5].tolist() == [0, 0]


def test_scoring_hashes_no_gram_by_itself(monkeypatch):
    """Most tokens of a large corpus are new, so a new token must not cost a call for each of its n-grams."""
    calls = []

    class Counted:
        @staticmethod
        def crc32(b):
            calls.append(b)
            return zlib.crc32(b)

    model = toxicity.ToxicityModel(toxicity.Inputs({"bad": 1.0}, {"^bad": 0.5}), toxicity.Network())
    texts = [" ".join(f"Word{i}number{j}" for j in range(100)) for i in range(20)] + ["x" * 300_000 + " y"]
    plain = np.concatenate([model.scores([t]) for t in texts])
    model.forget()
    monkeypatch.setattr(toxicity, "zlib", Counted)
    assert np.allclose(model.scores(texts), plain, atol=1e-6)
    assert len(calls) <= 2002


def test_windows_cover_every_word_and_overlap():
    for n in (1, 31, 32, 33, 48, 49, 500):
        doc, start, size = toxicity.windows(np.array([n, 5]))
        mine = [(s, z) for d, s, z in zip(doc, start, size) if d == 0]
        assert {i for s, z in mine for i in range(s, s + z)} == set(range(n))
        assert all(b[0] - a[0] == toxicity.STRIDE for a, b in zip(mine, mine[1:]))


def test_toxicity_held_out(spark):
    rng = random.Random(5)
    words = ["".join(rng.choice("abcdefghij") for _ in range(rng.randint(2, 6))) for _ in range(300)]
    rows, labels = [], []
    for i in range(700):
        t = [rng.choice(words) for _ in range(rng.randint(5, 200))]
        bad = i % 5 == 0
        if bad:
            for _ in range(3):
                t.insert(rng.randrange(len(t)), rng.choice(["Zuckwort", "zuckwerk,", "qqidiot", "qqmoron!"]))
        rows.append((i, " ".join(t), "en", "s"))
        labels.append((i, None, int(bad)))
    rows += [(None, "x", "en", "s"), (900, None, None, None), (901, " \n", "en", "s"), (902, "clean " * 20000 + "qqidiot qqmoron zuckwort", "en", "s")]
    lab = spark.createDataFrame([*labels, (None, 1, 1), (900, 1, None), (3, 1, 0)], "doc_id long, quality int, toxic int")
    got = {r.doc_id: r for r in toxicity.toxicity_report(documents(spark, rows), lab).collect()}
    held = [r for r in got.values() if r.held_out and r.doc_id is not None and r.doc_id < 700]
    assert len(held) > 80 and sum(r.predicted == (r.doc_id % 5 == 0) for r in held) / len(held) > 0.97
    assert got[900].score == got[901].score == 0.0 and got[902].predicted == 1
    assert {r.score for r in toxicity.toxicity_report(documents(spark, rows[:20]), lab.limit(0)).collect()} == {0.0}


# --- near duplicates ---------------------------------------------------------------------------------


def brute_components(rows, words, percent):
    def shingles(t):
        w = "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in t or "").replace("\x0b", " ").replace("\x0c", " ")
        w = [x for x in w.replace("\t", " ").replace("\n", " ").replace("\r", " ").split(" ") if x]
        return {tuple(w[i : i + words]) for i in range(max(1, len(w) - words + 1))} if w else set()

    sets = {d: shingles(t) for d, t in rows}
    comp = {d: d for d in sets}

    def root(x):
        while comp[x] != x:
            x = comp[x]
        return x

    ids = sorted(sets)
    for i, a in enumerate(ids):
        for b in ids[:i]:
            n = len(sets[a] & sets[b])
            if sets[a] and sets[b] and n * 100 >= percent * len(sets[a] | sets[b]):
                ra, rb = root(a), root(b)
                comp[max(ra, rb)] = min(ra, rb)
    return {d: (len(sets[d]), root(d)) for d in ids}


@pytest.mark.parametrize("words", [4, 5])
def test_near_duplicates_equal_brute_force(spark, words):
    rng = random.Random(words)
    vocab = [f"w{i}" for i in range(400)]
    rows, nxt = [], 10
    for _ in range(12):
        base = [rng.choice(vocab) for _ in range(rng.randint(40, 160))]
        for _ in range(rng.randint(1, 12)):
            t = list(base)
            for _ in range(rng.randint(0, 6)):
                t[rng.randrange(len(t))] = rng.choice(vocab)
            rows.append((nxt, " ".join(t)))
            nxt += rng.randint(1, 5)
            base = t if rng.random() < 0.5 else base  # chains
    rows += [(1, "Some SHORT"), (2, "some\tshort"), (3, "some"), (4, None), (5, ""), (6, " \n"), (7, "É a b c d"), (8, "é a b c d")]
    rows += [(1000 + i, "copy of a text that many have in common with each other") for i in range(30)]
    docs = documents(spark, [(d, t, "en", "s") for d, t in rows] + [(None, "null id", "en", "s"), (1, "Some SHORT", "en", "s")])
    got = near_dup.near_duplicates(docs, words=words, percent=80).collect()
    want = brute_components(rows, words, 80)
    assert len(got) == len(rows) + 2
    for r in got:
        if r.doc_id is None:
            assert r.component_id is None and r.kept
        else:
            assert (r.n_shingles, r.component_id) == want[r.doc_id] and r.kept == (r.doc_id == r.component_id), r
    assert near_dup.near_duplicates(docs.limit(0)).count() == 0


def test_open_clusters_are_compared_in_blocks(spark):
    """Sets that meet only through others, with blocks so small that each holds a few sets."""
    sets, rows = [], []
    for c in range(6):
        base = list(range(c * 1000, c * 1000 + 50))
        sets += [(c * 10 + k, base[:45] + [c * 1000 + 100 + k * 5 + i for i in range(5)]) for k in range(5)]
    rows = [(r, r, 0) for r, _ in sets]
    got = near_dup.cross_links(spark.createDataFrame(rows, "rep long, comp long, cluster long"), spark.createDataFrame(sets, "rep long, shingles array<long>"), 80, room=120)
    pairs = {(r.a, r.b) for r in got.collect()}
    assert pairs == {(c * 10 + i, c * 10 + j) for c in range(6) for i in range(5) for j in range(i + 1, 5)}


def test_share_of_links_met_at_the_threshold():
    """Of pairs of sets of similarity 0.80 to 0.82 nearly all share a table key."""
    rng = np.random.default_rng(8)
    met, n = 0, 3000
    for _ in range(n):
        common, own = 120, 15  # 120 of 150: exactly 0.80
        x = rng.integers(0, 1 << 62, common + 2 * own, dtype=np.uint64)
        a, b = (near_dup.sub_keys(np.unique(s), 12, 3) for s in (x[: common + own], np.r_[x[:common], x[common + own :]]))
        met += (a[:12] == b[:12]).any() and (a[12:] == b[12:]).any()
    assert met / n > 0.99


def test_fits_leave_the_driver(spark, monkeypatch):
    """Models are fitted inside a task: the driver's process never sees the sample, and gets the same model."""
    from bundlegraph.llm import toxicity

    rng = random.Random(4)
    vocab = {"de": ["haus", "baum", "straße"], "en": ["house", "tree", "street"]}
    rows = [(i, " ".join(rng.choices(vocab[lang], k=20)), lang) for i, lang in ((i, ["de", "en"][i % 2]) for i in range(60))]
    df = spark.createDataFrame(rows, "doc_id long, text string, lang string")
    labels = df.selectExpr("doc_id", "cast(doc_id % 3 = 0 as int) AS toxic")

    def refuse(*a, **k):
        raise AssertionError("fitted on the driver")

    monkeypatch.setattr(toxicity.DataFrame, "toArrow", refuse)
    language, model = langid.fit_languages(df), toxicity.fit_toxicity(df, labels)
    monkeypatch.undo()
    assert language.langs == ["de", "en"] and set(language.words) == {w for ws in vocab.values() for w in ws}
    assert len(language.words.table) == len(language.words) and language.words["haus"][0] > language.words["haus"][1]
    known = {r.doc_id: r.toxic for r in labels.collect()}
    same = toxicity.fit_network([t for _, t, _ in rows], [known[i] for i, _, _ in rows])
    assert abs(same.lift - model.lift) < 1e-3 and same.inputs.words == model.inputs.words
    none = langid.fit_languages(df.limit(0))
    assert none.langs == [] and len(none.words) == 0
