import hashlib
import random
import re
import zlib
from collections import Counter, defaultdict

import numpy as np
import public_tokenizers
import pytest
from gossipkit.llm import decontaminate, langid, minhash, mixing, neardup, packing, quality, queries, sharding, substring, tokenfile
from gossipkit.llm.oracles import ORACLES
from gossipkit.llm.textkernel import Words
from oracle import same
from pyspark.sql import Window
from pyspark.sql import functions as F
from tokenizers import Tokenizer

WORDS = re.compile(r"[^\x20\x09-\x0D]+")
ODD = [None, "", " \t\n ", "one", "a b c", "é\x0bü\x0cß 😀 x", "same words here " * 400, "x" * 20000, "a\x00b c", "a\x1cb\x85c"]


def frame(spark, texts, first=0):
    """Documents of these texts, with extra columns of clashing names."""
    rows = [(first + i, t, "en", "src0", len(t or ""), 7, "x", True) for i, t in enumerate(texts)]
    return spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long, topic int, slot string, kept boolean")


def made(seed, n, vocabulary=60):
    rng = random.Random(seed)
    base = [" ".join(rng.choice("abcdefgh") * rng.randint(1, 5) + str(rng.randint(0, vocabulary)) for _ in range(rng.randint(1, 60))) for _ in range(n // 3)]
    out = list(base)
    while len(out) < n:
        w = rng.choice(base).split()
        for _ in range(rng.choice([0, 1, 1, 2, 6])):
            w[rng.randrange(len(w))] = rng.choice("xyz") * 3
        out.append(rng.choice([" ", "\n"]).join(w))
    rng.shuffle(out)
    return out


@pytest.mark.parametrize("name", sorted(ORACLES))
def test_queries_equal_sql(spark, sf, name):
    same(spark, sf, queries.QUERIES[name], ORACLES[name])


def test_words_and_windows():
    texts = ["a bb  ccc", "", "a bb ccc a bb ccc", None, "é a"]
    w = Words(texts)
    assert [len(WORDS.findall(t or "")) for t in texts] == np.diff(w.first).tolist()
    h, ok = w.windows(3)
    assert ok.tolist()[:1] == [True] and h[0] == h[3] == h[6] and len(set(h[ok].tolist())) == 3


def test_packing_round_trip():
    k = np.sort(np.random.default_rng(0).integers(0, 2**48, 999).astype(np.uint64))
    assert (packing.unpack_sorted(packing.pack_sorted(k)) == k).all()
    assert packing.parted(packing.joined(b"a", b"", b"xyz")) == [b"a", b"", b"xyz"]


def cut_by_hand(texts):
    first, out = {}, {}
    for d, t in enumerate(texts):
        w = WORDS.findall(t or "")
        for i in range(len(w) - 12):
            first.setdefault(tuple(w[i : i + 13]), d)
    for d, t in enumerate(texts):
        w = WORDS.findall(t or "")
        gone = {i + j for i in range(len(w) - 12) if first[tuple(w[i : i + 13])] < d for j in range(13)}
        kept = " ".join(x for i, x in enumerate(w) if i not in gone)
        out[d] = (len(w), len(gone), hashlib.sha256(kept.encode()).hexdigest())
    return out


def test_substring_against_brute_force(spark):
    texts = ODD + made(1, 120, 9)
    rows = substring.dedup(frame(spark, texts)).collect()
    assert {r.doc_id: (r.n_words, r.n_removed, r.kept_sha256) for r in rows} == cut_by_hand(texts)
    assert sum(r.n_removed for r in rows) > 500
    assert substring.dedup(frame(spark, texts).limit(0)).count() == 0
    none = substring.dedup(frame(spark, [texts[-1]] * 2).withColumn("doc_id", F.lit(None).cast("long"))).collect()
    assert [r.n_removed for r in none] == [0, 0]


def groups_by_hand(texts, k=5):
    sets = []
    for t in texts:
        w = WORDS.findall("".join(c.lower() if "A" <= c <= "Z" else c for c in t or ""))
        sets.append({tuple(w[i : i + k]) for i in range(len(w) - k + 1)} if len(w) >= k else {tuple(w)} - {()})
    root = list(range(len(texts)))

    def find(i):
        while root[i] != i:
            i = root[i]
        return i

    for i, a in enumerate(sets):
        for j in range(i):
            if a and sets[j] and 100 * len(a & sets[j]) >= 85 * len(a | sets[j]):
                x, y = find(i), find(j)
                root[max(x, y)] = min(x, y)
    return {i: (len(s), find(i)) for i, s in enumerate(sets)}


def test_near_dedup_against_brute_force(spark):
    rng = random.Random(4)
    star = [f"w{i}" for i in range(120)]
    near = []
    for _ in range(60):  # near copies of one text, most not linked with each other
        w = list(star)
        for i in rng.sample(range(120), 2):
            w[i] = f"z{rng.random()}"
        near.append(" ".join(w).upper() if rng.random() < 0.3 else " ".join(w))
    texts = ODD + made(2, 150) + near + [" ".join(star)] + near[:5]
    rows = neardup.group(frame(spark, texts)).collect()
    assert {r.doc_id: (r.n_shingles, r.component_id) for r in rows} == groups_by_hand(texts)
    assert all(r.kept == (r.doc_id == r.component_id) for r in rows)
    assert neardup.group(frame(spark, texts).limit(0)).count() == 0
    kept = neardup.keep_first(frame(spark, texts))
    assert kept.columns == frame(spark, []).columns and kept.count() == sum(r.kept for r in rows)


def test_residual_links_in_blocks(spark, monkeypatch):
    """Links that the pivot does not see, with members dealt over several blocks."""
    monkeypatch.setattr(neardup, "BLOCK", 4)
    rng, texts = random.Random(8), []
    base = [f"w{i}" for i in range(200)]
    for c in range(6):  # families that differ from the base by a shared edit, so that only siblings are linked
        own = list(base)
        for i in range(c * 10, c * 10 + 8):
            own[i] = f"f{c}-{i}"
        for _ in range(5):
            w = list(own)
            w[rng.randrange(100, 200)] = f"z{rng.random()}"
            texts.append(" ".join(w))
    rng.shuffle(texts)
    rows = neardup.group(frame(spark, texts)).collect()
    assert {r.doc_id: (r.n_shingles, r.component_id) for r in rows} == groups_by_hand(texts)


def test_superminhash_estimates_with_less_variance():
    rng = np.random.default_rng(0)
    errors = []
    for _ in range(60):
        keys = rng.integers(0, 2**63, 60).astype(np.uint64)
        a, b = np.sort(keys[:50]), np.sort(keys[10:])
        s = minhash.signatures(np.concatenate([a, b]), np.array([0, 50, 100]), 150)
        errors.append((s[0] == s[1]).mean() - 40 / 60)
    assert abs(np.mean(errors)) < 0.02 and np.var(errors) < 40 / 60 * 20 / 60 / 150


def test_token_file(spark, tmp_path):
    path = public_tokenizers.path("byte_bpe_50k.json")
    tk = Tokenizer.from_file(path)
    texts = ODD[:-1] + ["a  b   c \n d\n\n e \t f", "  x", "x\n", "\nx", "won't, it's. a.. b, ...", "<|endoftext|> a<|endoftext|>b", "a\nb c.\nd, e"] + made(3, 40)
    docs = frame(spark, texts).repartition(5)
    out = str(tmp_path / "ids")
    tokenfile.write(docs, out, path)
    start = 0
    rows = {r.doc_id: r for r in tokenfile.read(spark, out, with_ids=True).collect()}
    for d, t in enumerate(texts):
        ids = [*tk.encode(t or "", add_special_tokens=False).ids, 2]
        r = rows[d]
        assert (r.ids, r.start, r.n_tokens) == (ids, start, len(ids)) and r.ids_crc32 == zlib.crc32(np.array(ids, "<u4").tobytes())
        start += len(ids)
    picked = {r.doc_id: r.ids for r in tokenfile.fetch(spark, out, [0, 3, 17, len(texts) - 1, 10**9]).collect()}
    assert picked == {d: rows[d].ids for d in (0, 3, 17, len(texts) - 1)}
    assert tokenfile.round_trip(docs.limit(0), path).count() == 0
    odd = docs.limit(3).select(F.lit(None).cast("long").alias("doc_id"), "text").union(docs.filter("doc_id < 4").select(F.lit(5).cast("long"), "text"))
    tokenfile.write(odd, str(tmp_path / "odd"), path)
    back = tokenfile.read(spark, str(tmp_path / "odd")).orderBy("start").collect()
    assert [r.doc_id for r in back] == [None] * 3 + [5] * 4 and [r.start for r in back][1:] == np.cumsum([r.n_tokens for r in back])[:-1].tolist()


def test_segments_joined_beyond_the_broadcast(spark, tmp_path, monkeypatch):
    path, docs = public_tokenizers.path("byte_bpe_50k.json"), frame(spark, made(3, 40))
    tokenfile.write(docs, str(tmp_path / "ids"), path)
    rows = lambda: sorted(map(tuple, tokenfile.read(spark, str(tmp_path / "ids")).collect()))
    one = rows()
    monkeypatch.setattr(tokenfile, "MAX_SEGMENTS", 0)
    assert one == rows() and len(one) == 40


@pytest.mark.parametrize("text", ["a  b", " a b", "a b\t", "word,' x's don't. end?! (so) $$$ a$$$ b_c_ _ --", "a<|endoftext|> <|endoftext|>b <|endoftext|>, c", "\u0120x \u0120 y", "x\u00a0y z\u2003 w\u3000,", "é̈, ñ!! 한국어. ʃ, ½% a1, 1a.", "a\0b \0 c"])
def test_pieces_equal_the_tokenizer(text):
    from gossipkit.llm.pieces import Encoder

    path = public_tokenizers.path("byte_bpe_50k.json")
    plain = Tokenizer.from_file(path).encode(text, add_special_tokens=False).ids
    assert np.frombuffer(next(Encoder(path).many([text])), "<u4").tolist() == plain


@pytest.mark.parametrize("n,top", [(1, 1), (1, 10**9), (300, 5), (5000, 10**7)])
def test_elias_fano(n, top):
    v = np.sort(np.random.default_rng(n).integers(0, top, n))
    ef = tokenfile.EliasFano.of(v)
    assert (ef.all() == v).all() and all(ef.select(i) == v[i] for i in range(0, n, max(n // 50, 1)))
    assert 8 * (len(ef.low) + len(ef.high)) <= n * (3 + max(np.log2(max(top / n, 1)), 0)) + 32


def test_language(spark, sf):
    docs = spark.read.parquet(sf.replace("0.001", "0.01") + "/documents.parquet")
    samples = langid.training_sample(docs)
    assert all(len(t) <= langid.SAMPLE_DOCS for t in samples.values()) and set(samples) == {"de", "en", "es", "fr"}
    rows = langid.identify(docs, samples).join(docs.select("doc_id", "lang"), "doc_id").collect()
    assert all(r.held_out == (zlib.crc32(str(r.doc_id).encode()) % 4 == 2) and 0 <= r.score <= 1 for r in rows)
    held = [r for r in rows if r.held_out]
    assert np.mean([r.lang_pred == r.lang for r in held]) > 0.98
    odd = {r.doc_id: r.lang_pred for r in langid.identify(frame(spark, ODD + ["1234 !!"]), samples).collect()}
    assert odd[0] == odd[1] == odd[2] == odd[len(ODD)] == "und" and odd[3] != "und"
    assert langid.identify(frame(spark, [chr(0x30001) * 3, chr(0x1F600)]), samples).orderBy("doc_id").collect()[0].lang_pred != "und"  # a letter of the third plane
    assert langid.identify(frame(spark, ["word"]), {}).first().lang_pred == "und"
    assert langid.identify(frame(spark, []), samples).count() == 0


def test_cross_parsing_against_brute_force():
    samples = {"a": ["the cat sat on the mat", "then the rat ran"], "b": ["el gato se sento", "en la alfombra roja"]}
    m = langid.Model(samples)
    texts = ["the rat sat in the hat", "la rata roja zz", "x" * 600]
    coded = [m.symbols(t) for t in texts]
    got = m.phrases(coded)
    for k, label in enumerate(m.labels):
        known = "\0".join(chr(97 + c) for c in np.concatenate([m.symbols(t) for t in samples[label]])).replace("\0", "")
        for i, c in enumerate(coded):
            n = 0
            for at in range(0, len(c), langid.BLOCK):
                s = "".join(chr(97 + x) for x in c[at : at + langid.BLOCK])
                n, cur = n + 1, ""
                for x in s:
                    if cur + x in known:
                        cur += x
                    else:
                        n, cur = n + 1, x if x in known else ""
            assert got[i, k] == n


def edits(a, b):
    row = list(range(len(b) + 1))
    for i, x in enumerate(a, 1):
        last, row[0] = row[0], i
        for j, y in enumerate(b, 1):
            last, row[j] = row[j], min(row[j] + 1, row[j - 1] + 1, last + (x != y))
    return row[-1]


def test_decontamination_recall_and_precision(spark):
    rng = random.Random(5)
    word = lambda: "".join(rng.choice("abcdefghij") for _ in range(5))
    items = [[word() for _ in range(rng.randint(6, 50))] for _ in range(40)]
    texts, want = [], []
    for d in range(400):
        noise, k = [word() for _ in range(rng.randint(0, 120))], rng.randrange(40)
        w = list(items[k])
        for _ in range(rng.randint(0, len(w) // 5)):
            i = rng.randrange(len(w))
            w[i : i + 1] = rng.choice([[], [word()], [w[i], word()]])
        if d % 2:
            at = rng.randint(0, len(noise))
            noise[at:at] = w
            want.append((d, k))
        texts.append(rng.choice([" ", "\n", ", "]).join(noise).upper())
    bench = spark.createDataFrame([(i, " ".join(w) + ".") for i, w in enumerate(items)] + [(90, None), (91, "a")], "item_id long, text string")
    found = decontaminate.search(frame(spark, texts), bench).collect()
    got = {(r.doc_id, r.item_id): r for r in found}
    assert len(set(want) - set(got)) <= len(want) * 0.01 and set(got) <= set(want)
    for r in found[:50]:
        assert r.distance <= max(r.item_words // 5, 0)
    clean = decontaminate.clean(frame(spark, texts), bench)
    assert clean.count() == 400 - len({d for d, _ in got}) and clean.columns == frame(spark, []).columns
    # a one-word item is found wherever that word stands
    assert sorted((r.doc_id, r.item_id) for r in decontaminate.search(frame(spark, ODD), bench).collect()) == [(4, 91), (8, 91), (9, 91)]
    assert decontaminate.search(frame(spark, []), bench).count() == 0
    assert decontaminate.search(frame(spark, texts), bench.limit(0)).count() == 0


def test_decontamination_against_brute_force(spark):
    """All items, short ones too, against all stretches of all texts; keys of other types, null ids, clashing columns."""
    rng = random.Random(11)
    vocabulary = [f"{c}{i}" for c in "abcdef" for i in range(12)]
    items = [[rng.choice(vocabulary) for _ in range(n)] for n in [1, 2, 2, 3, 4, 5, 5, *range(6, 40), 55, 80]]
    texts = []
    for d in range(300):
        w = [rng.choice(vocabulary[: rng.choice([20, 72])]) for _ in range(rng.randint(0, 60))]
        for _ in range(rng.randint(0, 2)):
            k = list(rng.choice(items))
            edits_ = rng.choice([0, len(k) // 5, len(k) // 5, len(k) // 5 + 1])
            lo = rng.choice([0, 0, max(len(k) - 2 * edits_ - 1, 0)])  # all over the item, or only at one end
            for _ in range(edits_):
                i = min(lo + rng.randrange(max(len(k) - lo, 1)), len(k) - 1)
                k[i : i + 1] = rng.choice([[], [rng.choice(vocabulary)], [k[i], rng.choice(vocabulary)]]) if len(k) > 1 else k
            at = rng.randint(0, len(w))
            w[at:at] = k
        texts.append(" ".join(w))

    def stretch(item, words):
        """Least edits of the item to any stretch."""
        row = [0] * (len(words) + 1)
        for i, x in enumerate(item, 1):
            last, row = row, [i]
            for j, y in enumerate(words, 1):
                row.append(min(last[j] + 1, row[-1] + 1, last[j - 1] + (x != y)))
        return min(row)

    want = {}
    for d, t in enumerate(texts):
        for k, item in enumerate(items):
            n = stretch(item, t.split())
            if n <= (len(item) // 5 if len(item) >= 6 else 0):
                want[d, k] = n
    bench = spark.createDataFrame([(f"item {i}", " ".join(w), "x") for i, w in enumerate(items)] + [(None, "zz zz", "x"), (None, None, "x")], "item_id string, text string, lang string")
    docs = frame(spark, [*texts, "q zz zz q"]).withColumn("doc_id", F.when(F.col("doc_id") < 300, F.col("doc_id"))).withColumn("distance", F.lit(1))
    found = decontaminate.search(docs, bench).collect()
    got = {(r.doc_id, int(r.item_id[5:])): r.distance for r in found if r.item_id}
    assert [(r.doc_id, r.distance, r.at_word) for r in found if not r.item_id] == [(None, 0, 1)]
    assert set(got) <= set(want) and len(got) >= 0.99 * len(want) and len(want) > 300
    assert all(n == want[x] for x, n in got.items())
    exact = {x for x, n in want.items() if not n}
    assert exact <= set(got)


def test_unrelated_windows_are_rejected():
    """The tables decide: texts of the benchmark's own words give next to no candidates."""
    rng = random.Random(12)
    vocabulary = [f"w{i}" for i in range(3000)]
    items = decontaminate.Items(list(range(200)), [" ".join(rng.choice(vocabulary) for _ in range(rng.randint(8, 50))) for _ in range(200)])
    text, tried = " ".join(rng.choice(vocabulary) for _ in range(20000)), []
    plain = decontaminate.nearest
    decontaminate.nearest = lambda a, n, b: tried.append(len(a)) or plain(a, n, b)
    try:
        assert items.search([text]) == []
    finally:
        decontaminate.nearest = plain
    assert sum(tried) < 20000 * 200 / 10000


def test_nearest_is_the_best_stretch():
    rng = np.random.default_rng(6)
    for _ in range(40):
        a, b = rng.integers(1, 5, rng.integers(3, 8)).astype(np.uint64), rng.integers(1, 5, rng.integers(3, 12)).astype(np.uint64)
        best = min(edits(a.tolist(), b[i:j].tolist()) for i in range(len(b) + 1) for j in range(i, len(b) + 1))
        pad = np.zeros((1, 9), np.uint64)
        pad[0, : len(a)] = a
        assert decontaminate.nearest(pad, np.array([len(a)]), b[None, :])[0] == best


def test_every_sampled_document_is_learned():
    rng = random.Random(3)
    texts = ["".join(rng.choice("abcdefghij") for _ in range(langid.DOC_SYMBOLS)) for _ in range(langid.SAMPLE_DOCS)]
    model = langid.Model({"xx": texts})
    # a block of any sampled document is one phrase
    assert all(model.phrases([model.symbols(t)[: langid.BLOCK]])[0, 0] == 1 for t in texts)


def test_blocks_of_items(spark, monkeypatch):
    monkeypatch.setattr(decontaminate, "MAX_WORDS", 8)
    bench = spark.createDataFrame([(i, f"a{i} b{i} c{i} d{i} e{i} f{i}") for i in range(4)], "item_id long, text string")
    docs = frame(spark, [f"x a{i} b{i} c{i} d{i} e{i} f{i} y" for i in range(4)] + ["nothing here"])
    assert {(r.doc_id, r.item_id) for r in decontaminate.search(docs, bench).collect()} == {(i, i) for i in range(4)}
    assert decontaminate.clean(docs, bench).count() == 1


def test_raking_meets_the_targets():
    rng = random.Random(1)
    rows = [(s, x, str(t), rng.random() * 100) for s in "abc" for x in ("de", "en") for t in range(3)]
    aims = [{"a": 0.5, "b": 0.3, "c": 0.2}, {"de": 0.6, "en": 0.4}, {"0": 0.2, "1": 0.3, "2": 0.5}]
    w, total = mixing.rake(rows, aims), sum(r[-1] for r in rows)
    for k, aim in enumerate(aims):
        for v, share in aim.items():
            assert abs(sum(w[r[:-1]] * r[-1] for r in rows if r[k] == v) / total - share) < 1e-6
    p = mixing.probabilities([r[-1] for r in rows], [w[r[:-1]] for r in rows], 0.6)
    assert max(p) <= 1 and abs(sum(a * r[-1] for a, r in zip(p, rows, strict=True)) / total - 0.6) < 1e-9


def test_mixing(spark, sf, monkeypatch):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    rows = mixing.mix(docs).collect()
    total = sum(r.n_tokens for r in rows)
    assert abs(sum(r.prob * r.n_tokens for r in rows) / total - mixing.SHARE) < 0.01
    assert all(r.kept == (int(hashlib.md5(f"{r.doc_id}/42".encode()).hexdigest()[:8], 16) / 2**32 < r.prob) for r in rows)
    small = mixing.with_topics(docs.filter("doc_id < 60").withColumn("source", F.lit("s"))).cache()
    one = {r[:3]: r.prob for r in mixing.plan(small, rounds=6).collect()}
    monkeypatch.setattr(mixing, "MAX_CELLS", 0)  # the way for cells too many for the driver
    other = {r[:3]: r.prob for r in mixing.plan(small, rounds=6).collect()}
    assert one.keys() == other.keys() and all(abs(one[k] - other[k]) < 1e-9 for k in one)
    assert mixing.decided(small, mixing.plan(small, rounds=1)).count() == small.count()
    monkeypatch.undo()
    assert mixing.mix(frame(spark, [])).count() == 0
    odd = mixing.mix(frame(spark, ODD).withColumn("lang", F.lit(None).cast("string"))).collect()
    assert len(odd) == len(ODD) and {r.topic for r in odd if not r.n_tokens} == {0}


def test_topics_find_planted_ones(spark):
    """Three topics in each of two languages; a topic is found whatever the language, and is not the language."""
    rng, rows = random.Random(9), []
    for d in range(900):
        topic, lang = d % 3, ["xx", "yy"][rng.random() < 0.3]
        common, own = [f"{lang}{i}" for i in range(40)], [f"{topic}t{i}" for i in range(25)]
        rows.append((d, " ".join(rng.choice(own if rng.random() < 0.4 else common) for _ in range(rng.randint(40, 200))), lang))
    seen = mixing.with_topics(spark.createDataFrame(rows, "doc_id long, text string, lang string"), topics=3).collect()
    votes = Counter((r.doc_id % 3, r.topic) for r in seen)
    best = [max(votes[t, k] for k in range(3)) for t in range(3)]
    assert sum(best) > 0.95 * 900 and len({max(range(3), key=lambda k: votes[t, k]) for t in range(3)}) == 3


def test_remixed_keeps_clashing_columns(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet").withColumns({c: F.lit(0.25) for c in ["_source", "_lang", "_topic", "_prob", "_copy", "topic", "n_tokens", "prob", "kept", "copies", "column0"]})
    out = mixing.remixed(docs)
    rows = out.collect()
    assert out.columns == docs.columns and rows and {(r.topic, r.prob, r.kept, r.column0) for r in rows} == {(0.25,) * 4}
    assert mixing.remixed(docs.limit(0)).count() == 0
    null = mixing.remixed(frame(spark, ODD + made(1, 30)).withColumns({c: F.lit(None).cast("string") for c in ["lang", "source"]}).withColumn("doc_id", F.lit(None).cast("long")))
    assert null.count() >= 0


def test_mixing_meets_the_targets(spark, sf, monkeypatch):
    docs = mixing.with_topics(spark.read.parquet(f"{sf}/documents.parquet")).drop("text").cache()
    cell = mixing.plan(docs)
    rows = cell.collect()
    total = sum(r.tokens for r in rows)
    kept = sum(r.tokens * r.prob for r in rows)
    assert abs(kept / total - mixing.SHARE) < 1e-9
    for k, d in enumerate(mixing.DIMS):
        for v, aim in mixing.tempered([r[:4] for r in rows], k).items():
            assert abs(sum(r.tokens * r.prob for r in rows if r[k] == v) / kept - aim) < 1e-3
    report = mixing.marginals(cell).collect()
    assert len(report) == sum(len({r[k] for r in rows}) for k in range(3)) and max(abs(r.got - r.target) for r in report) < 1e-3
    decided = mixing.decided(docs, cell).cache()
    seen = Counter(r.doc_id for r in mixing.sampled(decided).collect())
    for r in decided.collect():
        u = int(hashlib.md5(f"{r.doc_id}/42".encode()).hexdigest()[:8], 16) / 2**32
        assert r.copies == seen[r.doc_id] == sum(k + u < r.prob for k in range(int(r.prob) + 2)) and r.kept == (r.copies > 0)
    assert max(seen.values()) > 1
    with pytest.warns(UserWarning, match="misses a target"):
        bounded = mixing.plan(docs, repeats=False).collect()
    assert max(r.prob for r in bounded) <= 1
    # a target for a value without tokens can't be met
    with pytest.warns(UserWarning, match="by 0.5"):
        mixing.plan(docs, {"lang": {"en": 0.5, "xx": 0.5}})


def test_quality_against_brute_force(spark):
    texts = ODD + made(7, 60, 2) + ["l one\nl one\n\nl one\n two " * 9, "### $ | " * 30, "a b c d e f g h i " * 5]
    rows = {r.doc_id: r for r in quality.apply_policy(quality.ledger(frame(spark, texts))).collect()}
    for d, t in enumerate(texts):
        t = t or ""
        w = WORDS.findall(t)
        grams = Counter(tuple(w[i : i + 8]) for i in range(len(w) - 7))
        covered = {i + j for i in range(len(w) - 7) if grams[tuple(w[i : i + 8])] > 1 for j in range(8)}
        lines = [x for x in t.split("\n") if WORDS.search(x)]
        r = rows[d]
        want = (len(w), sum(map(len, w)), sum(c in "#*$%&|<>" for c in t), len(lines) - len(set(lines)), len(covered))
        assert (r.n_words, r.word_chars, r.n_symbols, r.n_dup_lines, r.n_repeat_words) == want
        assert r.base_failed == (len(w) < 20 or 100 * len(covered) > 30 * len(w)) and not (r.base_failed and r.kept)
    kept = quality.accepted(frame(spark, texts))
    assert kept.columns == frame(spark, []).columns and kept.count() == sum(r.kept for r in rows.values())
    led = quality.ledger(frame(spark, texts))
    for r in quality.ablation(led).collect():
        bit = 1 << list(quality.RULES).index(r.rule)
        assert r.failed == sum(bool(x.fail_bits & bit) for x in rows.values()) and r.rejected - r.rejected_without == r.only_by_rule
    assert quality.ledger(frame(spark, [])).count() == 0 and quality.accepted(frame(spark, [])).count() == 0
    clash = frame(spark, texts).withColumns({c: F.lit(-5) for c in ["_w", "_lines", "_h", "_s", "row", "whole", "fail_bits", "policy", *quality.MEASURES]})
    out = quality.accepted(clash)
    assert out.columns == clash.columns and out.count() == kept.count() and {r.n_words for r in out.collect()} == {-5}
    assert {r.doc_id: r.n_words for r in quality.ledger(clash).collect()} == {d: r.n_words for d, r in rows.items()}


def test_sharding(spark):
    names = [f"s{i}" for i in range(12)]
    table = sharding.fill(names)
    n = Counter(table)
    assert len(table) == sharding.prime_from(1200) and max(n.values()) - min(n.values()) <= 1
    weighted = Counter(sharding.fill(names, {"s0": 3}))
    assert weighted[0] > 2.5 * weighted[1]
    fewer = sharding.fill(names[:-1], slots=len(table))
    assert sharding.moved(table, fewer, names, names[:-1]) < 0.3  # a twelfth must move
    rows = sharding.assign(frame(spark, ODD), "doc_id", names).collect()
    assert len(rows) == len(ODD) and all(r.shard == table[r.slot] for r in rows)
    null = frame(spark, ["x"]).withColumn("doc_id", F.lit(None).cast("long"))
    assert sharding.assign(null, "doc_id", names).first().shard is not None and sharding.assign(frame(spark, []), "doc_id", names).count() == 0


def test_topics_are_fitted_on_all_documents(spark, monkeypatch):
    """More documents than the 4096 that the fit took before, whose ids have the least hashes; a topic that only the others have gets a
    centre of its own, whatever the partitioning."""
    one, two = " ".join(f"apple{i}" for i in range(30)), " ".join(f"engine{i}" for i in range(30))
    ids = spark.range(9000).withColumn("r", F.row_number().over(Window.orderBy(F.xxhash64("id"))))
    docs = ids.select(F.col("id").alias("doc_id"), F.when(F.col("r") <= 8000, one).otherwise(two).alias("text"), F.lit("en").alias("lang"), F.lit("web").alias("source")).cache()
    fits = [mixing.fitted(docs.repartition(n), topics=2) for n in (1, 7)]
    assert np.array_equal(fits[0].centres, fits[1].centres)
    got = mixing.with_topics(docs, topics=2).groupBy("text").agg(F.collect_set("topic").alias("t")).collect()
    assert sorted(r.t[0] for r in got) == [0, 1] and all(len(r.t) == 1 for r in got)


def test_mix_reads_the_texts_once(spark, sf, monkeypatch):
    plans, plain = [], mixing.stored

    def noted(df, label):
        plans.append(df._jdf.queryExecution().executedPlan().toString())
        return plain(df, label)

    monkeypatch.setattr(mixing, "stored", noted)
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    plans.append(mixing.mix(docs)._jdf.queryExecution().executedPlan().toString())
    assert sum("text:string" in p for p in plans) == 1
    monkeypatch.undo()
    # the topics are those of the way that reads the texts again
    ways = [{r.doc_id: (r.topic, r.n_tokens) for r in way.select("doc_id", "topic", "n_tokens").collect()} for way in (mixing.mix(docs), mixing.with_topics(docs))]
    assert ways[0] == ways[1]


def test_sums_of_stored_counts(spark):
    """Rows of one byte a number and of eight, in any mixture, come back as they were, and their sums by language are exact."""
    texts = ["a b a", None, "", "x " * 255, "y " * 256 + "z", *(f"w{i} " * (i % 300) for i in range(1500)), "é " * 70000]
    n = np.concatenate([x for x, _ in mixing.numbers(texts)])
    rows = mixing.packed(n)
    assert {len(r) for r in rows} == {mixing.FEATURES, 8 * mixing.FEATURES}
    for lo, hi in ((0, 3), (3, 5), (0, len(rows)), (5, 5)):
        ends = np.cumsum([0, *map(len, rows)])[lo : hi + 1]
        assert np.array_equal(mixing.unpacked(np.frombuffer(b"".join(rows), np.uint8), ends), n[lo:hi])
    langs = [None, "", "de", "en"]
    docs = spark.createDataFrame([(i, t, langs[i % 4]) for i, t in enumerate(texts)], "doc_id long, text string, lang string")
    x, want = np.rint(np.concatenate([x for x, _ in mixing.counted(texts)]) * np.float64(mixing.UNIT)), {}
    for i, r in enumerate(x):
        want[langs[i % 4]] = want.get(langs[i % 4], 0) + np.append(r / mixing.UNIT, 1)
    got = mixing.summed(mixing.counts(docs), lambda x, langs, code: (x, code, langs), "string")
    assert got.keys() == want.keys() and all(np.array_equal(got[k], want[k]) for k in want)
