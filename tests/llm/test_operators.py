import base64
import collections
import hashlib
import itertools
import random
import re
import zlib

import numpy as np
import pytest
import xxhash

from fieldtally.llm import bpe_pieces, cross_entropy, id_coder, jaccard_join, media_boxes, merkle, pii_tagger, quality, raking, repeats
from fieldtally.llm.components import components

WORD = re.compile(r"[^\x20\x09-\x0D]+")
EDGE = [(None, "no id"), (None, None), (1, None), (2, ""), (3, " \n "), (4, "one"), (5, "é" * 70), (6, "a b c d e"), (6, "a b c d e"), (7, "word " * 3000)]


def texts(spark, rows):
    """Documents with extra columns whose names might clash."""
    return spark.createDataFrame([(i, t, "x", 1, 2) for i, t in rows], "doc_id long, text string, n long, key int, bucket int".replace("n long", "n string"))


def prose(n, seed=3, words=60):
    r = random.Random(seed)
    return [(i, " ".join(f"w{r.randrange(words)}" for _ in range(r.randrange(0, 160)))) for i in range(n)]


@pytest.mark.parametrize("run", [
    lambda d: id_coder.read_ids(id_coder.write_ids(d)), jaccard_join.link_documents, pii_tagger.tag_documents, bpe_pieces.digest_documents,
    lambda d: repeats.remove_repeats(d, digest=True), media_boxes.store_texts, merkle.fingerprint_documents,
])
def test_edge_rows_and_empty_tables(spark, run):
    assert run(texts(spark, EDGE)).count() == len(EDGE)
    assert run(texts(spark, [])).count() == 0


def test_id_files():
    r, block = np.random.RandomState(1), id_coder.BLOCK
    zipf = np.minimum(r.zipf(1.3, 2 * block + 900), 40_000)
    for ids in (np.zeros(0, np.int64), np.arange(5), r.randint(0, 65535, block), np.repeat(r.randint(0, 500, 900), 40), zipf):
        data = id_coder.write_file(ids)
        assert (id_coder.read_file(data) == ids).all()
    assert (id_coder.read_file(data, 1, 3) == ids[block:]).all() and len(data) < 1.5 * len(ids)
    broken = bytearray(data)
    for at in (9, 30, -30):
        broken[at] ^= 255
        with pytest.raises(ValueError):
            id_coder.read_file(bytes(broken))
    with pytest.raises(ValueError):
        id_coder.write_file(np.array([70000]))


def test_a_block_needs_its_own_bytes_alone():
    block = id_coder.BLOCK
    one, two = np.random.RandomState(2).randint(0, 300, (2, block))
    together, alone = (id_coder.write_file(ids) for ids in (np.concatenate([one, two]), two))
    assert together.endswith(alone[24 + 12 :])


def test_chunks_have_the_ids_of_the_whole_text():
    import public_tokenizers
    from tokenizers import Tokenizer

    path = public_tokenizers.path("word_bpe_49k.json")
    coder, plain = id_coder.tokenizer(path), Tokenizer.from_file(path)
    odd = "I\u0307a it's IT'S. e\u0301t\u00e9, \u0130x \u0958a \u01c5abc\u00b2. \u2168 x\u2026.. a--b <|endoftext|> !!! \u1e9eA \ufb01n, K\u212a. \u03a3\u0391\u03a3. e\u0301. \u0e01\u0e33 don't. 'tis x_y 3.14, A9b! l'\u00c9t\u00e9;"
    for text in (odd, "", " \n\t", "word " * 3000, ".,;", odd.upper(), odd.replace(" ", "\u00a0"), "hello <|endoftext|> world<|startoftext|>x <|END|> <|endoftext|", "\x1c a\x85b ab\x00c"):
        assert coder.encode(text.encode()) == plain.encode(text, add_special_tokens=False).ids


def test_ids_of_documents(spark):
    import public_tokenizers
    from tokenizers import Tokenizer

    t = Tokenizer.from_file(public_tokenizers.path("word_bpe_49k.json"))
    rows = [(9, "Hello World's  ÉCOLE x"), (3, None), (5, "ΣΑΣ í 12 3!?")]
    start, want = 0, {}
    for i, text in sorted(rows):
        ids = [*t.encode(text or "", add_special_tokens=False).ids, 2]
        want[i] = (start, len(ids), zlib.crc32(np.array(ids, "<u4").tobytes()))
        start += len(ids)
    got = {r["doc_id"]: (r["start"], r["n_tokens"], r["ids_crc32"]) for r in id_coder.read_ids(id_coder.write_ids(texts(spark, rows))).collect()}
    assert got == want


def brute_links(rows):
    sets = {}
    for i, t in rows:
        w = WORD.findall((t or "").lower() if (t or "").isascii() else t)
        sets[i] = {tuple(w[k : k + 5]) for k in range(len(w) - 4)} or ({tuple(w)} if w else set())
    ids, up = list(sets), {i: i for i in sets}

    def top(x):
        while up[x] != x:
            x = up[x]
        return x

    for a in ids:
        for b in ids:
            if a < b and sets[a] and 100 * len(sets[a] & sets[b]) >= 75 * len(sets[a] | sets[b]):
                x, y = top(a), top(b)
                up[max(x, y)] = min(x, y)
    return {i: (len(s), top(i)) for i, s in sets.items()}


@pytest.mark.parametrize("crowd", [2, 64])
def test_jaccard_join(spark, crowd):
    r, rows = random.Random(5), []
    common = " ".join(f"c{i}" for i in range(20))
    for _ in range(25):
        base = [f"w{r.randrange(300)}" for _ in range(r.randrange(3, 60))]
        for _ in range(r.randrange(1, 9)):
            w = list(base)
            for _ in range(r.randrange(0, 4)):
                w[r.randrange(len(w))] = f"w{r.randrange(300)}"
            rows.append((len(rows), (common + " " if r.random() < 0.6 else "") + " ".join(w)))
    got = {x["doc_id"]: (x["n_shingles"], x["component_id"]) for x in jaccard_join.link_documents(texts(spark, rows), crowd).collect()}
    assert got == brute_links(rows)


def test_components(spark):
    edges = [(i, i + 1) for i in range(40)] + [(100, 101), (101, 100), (7, 7)]
    got = {r["node"]: r["component"] for r in components(spark, spark.createDataFrame(edges, "u long, v long")).collect()}
    assert all(got[i] == 0 for i in range(1, 41)) and got[101] == 100


def test_cross_entropy(spark):
    docs, target = [(1, "a b a c"), (2, None), (3, "x y a b")], ["a b a", "zz"]
    models = cross_entropy.build(texts(spark, docs), spark.createDataFrame([(t,) for t in target], "text string"), slots=1 << 16)
    got = {r["doc_id"]: r for r in cross_entropy.score(texts(spark, docs), models).collect()}
    corpora = [[t.split() for t in target], [(t or "").split() for _, t in docs]]
    size = len({w for c in corpora for t in c for w in t}) + 1

    def loss(corpus, words):
        one, ctx, two = collections.Counter(), collections.Counter(), collections.Counter()
        for t in corpus:
            for before, w in zip(["^", *t], t):
                one[w] += 1
                ctx[before] += 1
                two[before, w] += 1
        n = sum(one.values())
        return sum(-np.log((two[b, w] + 10 * (one[w] + 1) / (n + size)) / (ctx[b] + 10)) for b, w in zip(["^", *words], words)) / len(words)

    for i in (1, 3):
        words = dict(docs)[i].split()
        assert got[i]["target_loss"] == pytest.approx(loss(corpora[0], words), abs=1e-5)
        assert got[i]["background_loss"] == pytest.approx(loss(corpora[1], words), abs=1e-5)
    assert got[2]["difference"] is None and got[1]["difference"] < got[3]["difference"]


def test_cross_entropy_counts_every_word_and_bigram(spark):
    words = [f"w{i}" for i in range(70_000)]
    docs = [(1, " ".join(words)), (2, " ".join(words[::-1])), (None, " ".join(words[::3])), (4, ""), (5, None)]
    frame = texts(spark, docs).repartition(3)
    target = spark.createDataFrame([(" ".join(words[:2000]),)], "text string")
    got = {r["doc_id"]: r for r in cross_entropy.score(frame, cross_entropy.build(frame, target)).collect()}
    corpora = [[words[:2000]], [(t or "").split() for _, t in docs]]
    for model, name in enumerate(["target_loss", "background_loss"]):
        one, ctx, two = collections.Counter(), collections.Counter(), collections.Counter()
        for t in corpora[model]:
            one.update(t)
            ctx.update(["^", *t][:-1] if t else [])
            two.update(zip(["^", *t], t))
        n, size = sum(one.values()), len(words) + 1
        for doc_id, text in docs[:3]:
            t = text.split()
            p = [(two[h, w] + 10 * (one[w] + 1) / (n + size)) / (ctx[h] + 10) for h, w in zip(["^", *t], t)]
            assert max(p) <= 1 and got[doc_id][name] == pytest.approx(-np.log(p).mean(), abs=1e-7)
    assert got[4]["difference"] is None and got[5]["n_tokens"] == 0 and len(got) == len(docs)
    # The same scores whether the documents are those the models are counted over, or others.
    whole = sorted(tuple(r) for r in cross_entropy.score(texts(spark, prose(60)), cross_entropy.build(texts(spark, prose(60)), target)).collect())
    frame = texts(spark, prose(60))
    assert sorted(tuple(r) for r in cross_entropy.score(frame, cross_entropy.build(frame, target)).collect()) == whole


def test_pii_base_and_tagger(spark):
    text = "é mail a.b@c.de, 10.0.0.1 and 999.1.1.1; card 4111 1111 1111 1111 tel +49 (30) 123-4567 x@@y @z.q 1.2.3.4.5"
    spans = [(k, text[a:b]) for k, a, b in pii_tagger.base_spans(text)]
    assert spans == [("email", "a.b@c.de"), ("ip", "10.0.0.1"), ("ip", "1.2.3.4"), ("card", "4111 1111 1111 1111"), ("phone", "+49 (30) 123-4567")]
    ids, tags = pii_tagger.labelled_windows(300, np.random.RandomState(77))
    assert (pii_tagger.viterbi(pii_tagger.trained(), ids) == tags).mean() > 0.95
    kept = pii_tagger.redact(texts(spark, [(1, text), (2, None), (3, "clean prose")])).orderBy("doc_id").collect()
    assert "<EMAIL>" in kept[0]["text"] and "4111" not in kept[0]["text"] and kept[1]["text"] is None and kept[2]["text"] == "clean prose"
    base, every = pii_tagger.find_spans(pii_tagger.trained(), [text * 20])[0]
    assert set(base) <= set(every)


def brute_base(text):
    """The base patterns as stated, with Python's regular expressions alone."""
    digits = lambda t: [int(c) for c in t if c in "0123456789"]
    good = {
        "email": lambda t: True,
        "ip": lambda t: all(int(p) <= 255 for p in t.split(".")),
        "card": lambda t: 16 <= len(digits(t)) <= 19 and sum(sum(divmod(d * (1 + i % 2), 10)) for i, d in enumerate(digits(t)[::-1])) % 10 == 0,
        "phone": lambda t: 8 <= len(digits(t)) <= 15,
    }
    patterns = {"email": r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+", "ip": r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)", "card": r"[0-9]([\x20-]?[0-9])+", "phone": r"\+[0-9][\x20().0-9-]+[0-9]"}
    return [(k, *m.span()) for k, p in patterns.items() for m in re.finditer(p, text) if good[k](m[0])]


def test_pii_base_equals_brute_force(spark):
    r = random.Random(4)
    rows = [(i, "".join(r.choice("ab.@-+() 0123456789\u00e9\n") for _ in range(r.randrange(0, 120)))) for i in range(400)]
    rows += [(1000 + i, x["text"]) for i, x in enumerate(spark.read.parquet("/root/testdata/sf0.001/documents.parquet").select("text").collect())]
    got = {x["doc_id"]: x for x in pii_tagger.tag_documents(texts(spark, rows)).collect()}
    for i, t in rows:
        base = brute_base(t or "")
        joined = ",".join(f"{k}:{a}:{b}" for k, a, b in base)
        assert got[i]["base_sha256"] == hashlib.sha256(joined.encode()).hexdigest()
        assert [got[i][f"n_{k}"] for k in pii_tagger.KINDS] == [sum(b[0] == k for b in base) for k in pii_tagger.KINDS]
        assert {f"{k}:{a}:{b}" for k, a, b in base} <= set(got[i]["spans"].split(","))


def test_pii_spans_beyond_the_base_patterns():
    rng, p, r = np.random.RandomState(901), pii_tagger.trained(), random.Random(7)
    prose, wanted = [], []
    word = lambda: "".join(r.choice(("er", "on", "ti", "the", "sha", "ou", "in", "\u00e9", "re")) for _ in range(r.randrange(1, 4)))
    for _ in range(600):
        text, (snippet, kind) = " ".join(word() for _ in range(r.randrange(3, 25))) + " ", pii_tagger._draw(rng)
        prose.append(f"{text}{snippet} {' '.join(word() for _ in range(8))}")
        wanted.append((kind, len(text), len(text) + len(snippet)))
    found, missed, wrong = 0, 0, 0
    for (kind, a, b), (base, every) in zip(wanted, pii_tagger.find_spans(p, prose), strict=True):
        added = [s for s in every if s not in base]
        if kind and (kind, a, b) not in base:
            hit = any(x < b and a < y for _, x, y in added)
            found, missed = found + hit, missed + (not hit)
        wrong += sum(not kind or y <= a or b <= x for _, x, y in added)
    assert found > 0.85 * (found + missed) and wrong < 0.05 * found


def test_bpe(spark):
    import tiktoken

    path, pattern = bpe_pieces.default_vocabulary()
    ranks = {base64.b64decode(a): int(b) for a, b in map(bytes.split, open(path, "rb"))}
    own = tiktoken.Encoding("own", pat_str=pattern, mergeable_ranks=ranks, special_tokens={})
    rows = [(1, "Hello, wörld's  \n\n x"), (2, None), (3, "🙂" * 5 + " " * 50 + "z" * 3000)]
    got = {r["doc_id"]: r for r in bpe_pieces.encode_documents(texts(spark, rows)).collect()}
    for i, t in rows:
        assert np.frombuffer(got[i]["ids"], "<u4").tolist() == own.encode_ordinary(t or "") and bytes(got[i]["decoded"]).decode() == (t or "")


def test_repeats(spark):
    r, rows = random.Random(2), []
    pieces = [" ".join(f"w{r.randrange(40)}" for _ in range(r.randrange(20, 80))) for _ in range(15)]
    for i in range(80):
        rows.append((i, " ".join(r.choice(pieces) if r.random() < 0.4 else f"u{r.randrange(9999)}" for _ in range(r.randrange(0, 8)))))
    rows += [(100, "a " * 90), (101, "a b " * 40), (102, None)]
    split = [(i, WORD.findall(t or "")) for i, t in rows]
    seen = collections.Counter(tuple(w[k : k + 35]) for _, w in split for k in range(len(w) - 34))
    want = {}
    for i, w in split:
        gone = {p for k in range(len(w) - 34) if seen[tuple(w[k : k + 35])] > 1 for p in range(k, k + 35)}
        want[i] = (len(w), len(gone), hashlib.sha256(" ".join(x for p, x in enumerate(w) if p not in gone).encode()).hexdigest())
    assert {x["doc_id"]: tuple(x)[1:] for x in repeats.remove_repeats(texts(spark, rows), digest=True).collect()} == want


def test_words_and_blocks_of_a_bucket():
    import pyarrow as pa

    column = pa.array(["x", "a b\u00a0c", None, "", " \t lead", "tail\n", "no", "gap", " ", "a b " * 30])[1:]
    words = repeats.Words(pa.chunked_array([column[:4], column[4:]]))
    flat, split = words.flat.to_pylist(), [(t or "").encode().split() for t in column.to_pylist()]
    assert [flat[a:b] for a, b in itertools.pairwise(words.bounds.tolist())] == split
    assert [xxhash.xxh3_64_intdigest(w) for w in flat] == words.hashes.tolist()
    assert np.flatnonzero(words.whole()).tolist() == list(range(words.bounds[-2], words.bounds[-1] - 34))
    # Every window has one whole block, and the automata hold less than a third of the words they are compiled from.
    starts = np.flatnonzero(np.random.RandomState(5).rand(3000) < 0.97)
    blocks = repeats.blocks_of(starts)
    assert all(((blocks >= s) & (blocks + repeats.BLOCK <= s + 35)).any() for s in starts)
    whole = repeats.blocks_of(np.arange(2801))
    assert whole[-1] + repeats.BLOCK <= 2835 and len(whole) * repeats.BLOCK < 2835 / 3


def test_media_of_documents(spark):
    rows = [*EDGE, (9, "\u00e9" * 5000)]
    frame = spark.createDataFrame(rows, "doc_id long, text string").mapInArrow(media_boxes._digests, media_boxes.DIGEST_SCHEMA)
    wanted = []
    for i, t in rows:
        raw = (t or "").encode()
        padded = raw + b"\0" * ((64 - len(raw) % 64) % 64 if raw else 64)
        stored = media_boxes.write_container(padded)
        assert padded in stored
        wanted.append((i or 0, len(raw), len(padded), hashlib.sha256(padded).hexdigest(), zlib.crc32(padded[-64:]), len(stored), hashlib.sha256(stored).hexdigest()))
    assert sorted((x["doc_id"] or 0, *tuple(x)[1:7]) for x in frame.collect()) == sorted(wanted)


def test_media(spark):
    for raw in (b"", b"x", bytes(range(256)) * 41):
        data = media_boxes.write_container(media_boxes.pad(raw))
        (track,) = media_boxes.inspect(data)
        assert media_boxes.payload_of(data, track) == media_boxes.pad(raw) and track.duration == len(media_boxes.pad(raw))
        assert (track.keyframes[:, 1] - track.keyframes[:, 0] == 64).all()
    for damaged in (data[:100], data[:-1], b"\0\0\0\7junk"):
        with pytest.raises(ValueError):
            media_boxes.inspect(damaged)
    deep = b""
    for _ in range(1200):
        deep = media_boxes._box(b"moov", deep)
    many = data.replace(b"stsz" + bytes(4) + (64).to_bytes(4, "big") + (len(media_boxes.pad(raw)) // 64).to_bytes(4, "big"), b"stsz" + bytes(4) + (64).to_bytes(4, "big") + b"\xff\xff\xff\xff")
    run = data.index(b"stsc") + 12
    for hostile in (deep, many, data[:run] + b"\xff\xff\xff\xf0" + data[run + 4 :], data[:run] + b"\0\0\0\0" + data[run + 4 :]):
        assert hostile != data
        with pytest.raises(ValueError):
            media_boxes.inspect(hostile)
    out = media_boxes.describe_media(spark.createDataFrame([(1, data), (2, b"junk"), (3, None)], "doc_id long, media binary")).orderBy("doc_id").collect()
    assert out[0]["codec"] == "raw " and out[1]["codec"] is None and out[2]["keyframes"] is None


def test_quality(spark):
    r = random.Random(1)
    rows = [(i, " ".join(f"w{r.randrange(80)}" for _ in range(40))) if i % 2 else (i, " ".join(f"W{r.randrange(80)}$$$" for _ in range(40))) for i in range(160)]
    labels = spark.createDataFrame([(i, i % 2) for i, _ in rows] + [(9999, 1), (None, 0)], "doc_id long, quality int")
    docs = texts(spark, [*rows, *((i and 1000 + i, t) for i, t in EDGE)])
    got = quality.score_documents(docs, quality.train(docs, labels)).collect()
    assert len(got) == docs.count() and all(0 <= x["score"] <= 1 and x["predicted"] == (x["score"] >= 0.7) for x in got)
    held = [x for x in got if x["held_out"] and x["doc_id"] < 160]
    assert held and np.mean([x["predicted"] == x["doc_id"] % 2 for x in held]) > 0.95
    assert all(x["held_out"] == (x["doc_id"] is not None and zlib.crc32(str(x["doc_id"]).encode()) % 4 == 2) for x in got)
    assert quality.fit([b"a"], [1]).score([b"", b"b"]).tolist() == [1.0, 1.0]


def test_quality_of_held_out_documents(spark):
    sf = "/root/testdata/sf0.01"
    docs, labels = spark.read.parquet(f"{sf}/documents.parquet"), spark.read.parquet(f"{sf}/labels.parquet")
    scored = quality.score_documents(docs, quality.train(docs, labels)).where("held_out").join(labels, "doc_id").select("score", "quality").collect()
    good, bad = ([x["score"] for x in scored if x["quality"] == q] for q in (1, 0))
    assert np.mean([(a > b) + 0.5 * (a == b) for a in good for b in bad]) > 0.9
    many = docs.where("doc_id < 200").unionByName(docs.where("doc_id < 200")).unionByName(docs.where("doc_id < 200"))
    texts_, marks = quality.labelled_sample(many, labels, 50)
    assert len(texts_) == len(marks) <= 50


def test_merkle_of_ids_of_any_size(spark):
    ids = [-(2**63), -(2**62), -5, None, 0, 7, 2**62, 2**63 - 1]
    rows = [(i, f"text {i}") for i in ids]
    got = {r["doc_id"]: r for r in merkle.fingerprint_documents(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    line = sorted((i for i in ids if i is not None)) + [None]
    for i, after in zip(line, [*line[1:], line[0]], strict=True):
        own, other = f"text {i}", f"text {after}"
        assert got[i]["edited_sha256"] == hashlib.sha256((own[: len(own) - len(own) // 2] + other[: len(own) // 2]).encode()).hexdigest()


def test_merkle(spark):
    rows = [(3, "One. Two.\nThree\n\nFour"), (1, "One. Two.\nThrice\n\nFour"), (2, None), (9, "One. Two.\nThree\n\nFour")]
    got = {r["doc_id"]: r for r in merkle.fingerprint_documents(texts(spark, rows)).collect()}
    assert got[3]["fingerprint"] == got[9]["fingerprint"] != got[1]["fingerprint"] and got[3]["near_next"] == 1.0
    text = dict(rows)
    for i, after in ((1, 2), (2, 3), (3, 9), (9, 1)):
        own, other = text[i] or "", text[after] or ""
        half = len(own) // 2
        assert got[i]["edited_sha256"] == hashlib.sha256((own[: len(own) - half] + other[:half]).encode()).hexdigest()
    pair = spark.createDataFrame([(got[3]["fingerprint"], got[1]["fingerprint"])], "a string, b string")
    assert pair.select(merkle.differing_paragraphs(pair["a"], pair["b"])).first()[0] == [1]


def test_raking_meets_marginals(spark):
    r = random.Random(3)
    rows = [(i, "w " * r.randrange(1, 30), r.choice(["en", "en", "de"]), r.choice("abbb"), r.choice("pq")) for i in range(600)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, topic string")
    wanted = {"source": spark.createDataFrame([("a", 0.5), ("b", 0.5), ("zz", 0.3)], "value string, target double").where("value <> 'zz'")}
    out = raking.mix(docs, wanted, rounds=30, keep=0.2).select("_mix.*").toPandas()
    mass = out.assign(w=out.tokens * out.probability).groupby("source").w.sum()
    assert abs(mass["a"] / mass.sum() - 0.5) < 0.01 and abs(mass.sum() / out.tokens.sum() - 0.2) < 0.02
    assert set(out.kept) == {True, False} and raking.sample(docs).columns == docs.columns
    assert raking.mix(docs.limit(0)).count() == 0
    nothing = spark.createDataFrame([(None, None, None, None)], "doc_id long, text string, lang string, source string")
    assert raking.mix(nothing).select("_mix.probability").first()[0] == raking.KEEP


def test_pipeline_keeps_columns(spark):
    import corpus_pipeline

    docs = corpus_pipeline.read_documents(spark, "/root/testdata/sf0.001")
    for _, stage in corpus_pipeline.STAGES[:-1]:
        docs = corpus_pipeline.scratch(spark, stage(spark, docs, "/root/testdata/sf0.001"), "t")
        assert docs.columns == ["doc_id", "text", "lang", "source", "n_chars"]
    n = docs.count()
    assert 0 < n < 200 and corpus_pipeline.byte_pairs(spark, docs, "/root/testdata/sf0.001").count() == n


def test_keep_first_keeps_all_rows_without_an_id(spark):
    rows = [(None, "one two three four five six"), (None, "other words"), (None, None), (1, "a b c d e f"), (1, "a b c d e f"), (2, "a b c d e f"), (3, "x y")]
    got = jaccard_join.keep_first(texts(spark, rows))
    assert sorted((r["doc_id"] or 0, r["text"] or "") for r in got.collect()) == [(0, ""), (0, "one two three four five six"), (0, "other words"), (1, "a b c d e f"), (3, "x y")]
    assert got.columns == texts(spark, []).columns
