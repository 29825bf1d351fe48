import hashlib
import random
import re
import zlib

import numpy as np
import public_tokenizers as P
import pytest
import tiktoken
import xxhash
from pyspark.sql import functions as F
from tokenizers import Tokenizer

from polyedge.llm import bpe, chat, common, fingerprints, packing, quality, queries, secrets, simhash, token_counts, toxicity, webp

LONG = "Very long text without an end, and then some.\n" * 4000
TEXTS = [None, "", " ", "\n\n\t", "one", "two words", "a b c", "A B C", LONG, LONG, "password = hunter2hunter2", "日本語 ñ é ß 😀 x y", "a  double  space\n\nand lines\n"]


@pytest.fixture(scope="module")
def docs(spark):
    rows = [(i, t, "s", "x", "y") for i, t in enumerate(TEXTS)] + [(None, "no id", "s", "x", "y"), (3, "\n\n\t", "s", "x", "y")]
    return spark.createDataFrame(rows, "doc_id long, text string, source string, lang string, score string").cache()


@pytest.fixture(scope="module")
def none(spark):
    return spark.createDataFrame([], "doc_id long, text string, source string, lang string, score string")


def by_id(df, key="doc_id"):
    return {r[key]: r.asDict() for r in df.collect()}


# ------------------------------------------------------------------ secrets


def brute_spans(text):
    out = []
    for m in re.finditer(r"""(password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", text, re.I | re.A):
        if len(m.group(2)) >= 6:
            out.append((m.start(), 0, f"assign:{m.start()}:{m.end()}"))
    out += [(m.start(), 1, f"access:{m.start()}:{m.end()}") for m in re.finditer("AKIA[A-Z0-9]+", text) if len(m.group()) >= 20]
    out += [(m.start(), 2, f"hex:{m.start()}:{m.end()}") for m in re.finditer("[0-9a-f]+", text) if len(m.group()) >= 24]
    return [s for _, _, s in sorted(out)]


def test_secret_base_spans_match_the_plain_patterns():
    rng = random.Random(5)
    bits = ["token", "secret=", "SECRET: ", "api_key", "apikey=", '"', "'", " ", ":", "=", "abc", "deadbeef", "0123456789abcdef", "AKIA", "ABCDEF0123456789", "ſecret=abcdefgh", "é", "\n"]
    model = secrets.fit(*secrets.default_samples())
    for _ in range(3000):
        t = "".join(rng.choices(bits, k=rng.randint(0, 14)))
        got = [f"{k}:{a}:{b}" for k, a, b in model.spans(t) if k != "markov"]
        assert got == brute_spans(t), t


@pytest.mark.parametrize("kind", sorted(secrets.KEY_ALPHABETS))
def test_secret_model_finds_random_strings(kind):
    model, rng = secrets.default_model(), random.Random(2)
    for size in (16, 20, 32, 64):
        found = sum(model.is_random("".join(rng.choices(secrets.KEY_ALPHABETS[kind], k=size))) for _ in range(200))
        assert found >= (190 if size == 16 else 197), size


def test_secret_model_error_rates_and_names():
    model = secrets.default_model()
    assert model.missed < 0.005 and model.wrong < 0.001
    fresh = secrets.ordinary_samples(random.Random(77), 300)
    assert sum(model.is_random(s) for x in fresh.values() for s in x) <= 0.003 * 300 * len(fresh)
    for name in ["get_user_profile_by_name", "configuration2024/index.html", "mail2.example.com/static", "THIS_IS_A_CONSTANT_VALUE", "1234567890123456789012", "x" * 40, "abcdefghijklmnopqrstuvwxyz", "UnterhaltungselektronikGeschaeft"]:
        assert not model.is_random(name), name


def test_secret_model_from_a_table(spark):
    keys, names = secrets.default_samples(seed=3, each=300)
    rows = [(s, k, y) for y, kinds in ((True, keys), (False, names)) for k, x in kinds.items() for s in x]
    model = secrets.fit_labelled(spark.createDataFrame([*rows, (None, "x", True), ("x", None, None)], "text string, kind string, is_random boolean"))
    assert model.is_random("q8Zr2LxV0tYb7KpWmN4cHs9dJe3U") and not model.is_random("get_user_profile_by_name")
    with pytest.raises(ValueError):
        secrets.fit_labelled(spark.createDataFrame(rows[:1], "text string, kind string, is_random boolean"))


def test_secret_scan_cases(spark, docs, none):
    model = secrets.default_model()
    got = by_id(secrets.digest(docs, model))
    assert got[10]["n_assign"] == 1 and got[0]["spans"] == "" and len(got) == len(TEXTS) + 1
    assert secrets.digest(none, model).count() == 0
    clean = secrets.redact(docs, model)
    assert clean.count() == docs.count()
    assert by_id(clean)[10]["redacted_text"] == "[assign removed]"
    assert by_id(clean)[8]["redacted_text"] == LONG


# ------------------------------------------------------------------ classifiers


def labelled(spark, n=300):
    rng = random.Random(1)
    words = ["alpha", "beta", "gamma", "delta", "river", "stone", "cloud"]
    rows, labels = [], []
    for i in range(n):
        t = " ".join(rng.choices(words, k=30))
        bad, junk = i % 4 == 0, i % 5 == 0
        t = t + " you grobblewit" if bad else t
        t = " ".join(w + "!!" for w in t.upper().split()) if junk else t
        rows.append((i, t))
        labels.append((i, int(not junk), int(bad)))
    return spark.createDataFrame(rows, "doc_id long, text string"), spark.createDataFrame(labels, "doc_id long, quality int, toxic int")


def test_classifiers_learn_held_out_rows(spark):
    d, lab = labelled(spark)
    truth = {r.doc_id: r for r in lab.collect()}
    use = F.crc32(F.col("doc_id").cast("string")) % 5 != 0
    for module, column in ((quality, "quality"), (toxicity, "toxic")):
        model = module.fit(d, lab, column, use=use)
        held = [r for r in module.score(d, model).collect() if zlib.crc32(str(r.doc_id).encode()) % 5 == 0]
        assert len(held) > 30
        assert np.mean([r.predicted == truth[r.doc_id][column] for r in held]) > 0.95
        assert all(0 <= r.score <= 1 for r in held)


@pytest.mark.parametrize("module", [quality, toxicity])
def test_classifier_cases(spark, docs, none, module):
    d, lab = labelled(spark, 60)
    column = "quality" if module is quality else "toxic"
    model = module.fit(d, lab, column)
    got = module.score(docs, model)
    assert got.count() == docs.count() and dict(got.dtypes)["score"] == "double"
    assert module.score(none, model).count() == 0
    one_sided = module.fit(d, lab.where(f"{column} = 1"), column)
    assert {round(r.score, 3) for r in module.score(docs, one_sided).collect()} == {1.0}
    untrained = module.fit(d, lab.limit(0), column, default_score=0.0)
    assert {r.predicted for r in module.score(docs, untrained).collect()} == {0}
    nulls = lab.unionByName(spark.createDataFrame([(None, 1, 1), (5, None, None)], lab.schema))
    assert module.score(docs, module.fit(d, nulls, column)).count() == docs.count()


# ------------------------------------------------------------------ fingerprints

PAR = re.compile(r"[^\n]{1,120}[^\n.!?]{0,400}[.!?]*\n?|\n")


def likeness(a, b):
    x, y = set(PAR.findall(a)), set(PAR.findall(b))
    return len(x & y) / len(x | y) if x | y else 1.0


def test_fingerprints_against_brute_force(spark):
    rng = random.Random(3)
    texts = [None, "", "x", "é\nß", LONG] + ["\n".join(f"line {rng.randint(0, 40)} of text." for _ in range(rng.randint(0, 90))) for _ in range(60)]
    texts += [texts[10], texts[10]]
    ids = [3 * i - 20 for i in range(len(texts))]
    d = spark.createDataFrame(list(zip(ids, texts)), "doc_id long, text string")
    got = by_id(fingerprints.edit_and_fingerprint(d.repartition(5), buckets=7))
    t = [x or "" for x in texts]
    for i, (k, x) in enumerate(zip(ids, t)):
        nxt = t[(i + 1) % len(t)]
        half = len(x) // 2
        edited = x[: len(x) - half] + nxt[:half]
        r = got[k]
        assert r["n_chars"] == len(x) and r["edited_sha256"] == hashlib.sha256(edited.encode()).hexdigest()
        assert r["near_edited"] == pytest.approx(likeness(x, edited)) and r["near_next"] == pytest.approx(likeness(x, nxt))
        assert (r["fingerprint"] == r["edited_fingerprint"]) or x != edited
    assert got[ids[-1]]["fingerprint"] == got[ids[-2]]["fingerprint"]


def test_fingerprint_cases(spark, docs, none):
    assert fingerprints.edit_and_fingerprint(docs).count() == docs.count()
    assert fingerprints.edit_and_fingerprint(none).count() == 0
    one = spark.createDataFrame([(7, "alone")], "doc_id long, text string")
    assert fingerprints.edit_and_fingerprint(one).first().near_next == 1.0
    only_null = spark.createDataFrame([(None, "a"), (None, None)], "doc_id long, text string")
    assert fingerprints.edit_and_fingerprint(only_null).count() == 2


def test_version_difference_recovers_the_digests(spark):
    old = "\n".join(f"paragraph {i}" for i in range(300))
    new = old.replace("paragraph 7\n", "changed\n").replace("paragraph 200\n", "")
    r = fingerprints.version_difference(spark.createDataFrame([(old, new, "z")], "a string, b string, added string"), "a", "b").first()
    digest = lambda s: spark.sql("SELECT xxhash64(:s) AS h", {"s": s}).first().h
    assert sorted(r.removed) == sorted([digest("paragraph 7\n"), digest("paragraph 200\n")])
    assert r.added == [digest("changed\n")]


# ------------------------------------------------------------------ simhash


def brute_print(text):
    w = (text or "").encode().lower().split()
    w = [x for x in w if x]
    s = [b" ".join(w[i : i + 3]) for i in range(max(1, len(w) - 2))] if w else []
    h = [xxhash.xxh64_intdigest(x, 42) for x in s]
    return sum(1 << b for b in range(64) if 2 * sum(x >> b & 1 for x in h) > len(h)) if h else 0


def brute_components(fps, threshold=2):
    root = list(range(len(fps)))

    def find(i):
        while root[i] != i:
            root[i] = root[root[i]]
            i = root[i]
        return i

    for i in range(len(fps)):
        for j in range(i):
            if (fps[i] ^ fps[j]).bit_count() <= threshold:
                a, b = sorted((find(i), find(j)))
                root[b] = a
    return [find(i) for i in range(len(fps))]


def test_fingerprint_is_the_majority_of_shingle_hashes():
    for t in TEXTS[:8] + TEXTS[10:]:
        assert simhash.fingerprint(t or "") == brute_print(t)


@pytest.mark.parametrize("cap", [512, 3])
def test_links_lose_nothing(spark, cap):
    rng = random.Random(8)
    fps = [0]
    for _ in range(40):
        x = rng.getrandbits(64)
        fps.append(x)
        for _ in range(rng.randint(0, 12)):
            for b in rng.sample(range(64), rng.randint(1, 3)):
                x ^= 1 << b
            fps.append(x)
    fps = sorted(set(fps))
    want = brute_components(fps)
    signed = [x - (1 << 64) if x >> 63 else x for x in fps]
    d = spark.createDataFrame([(x,) for x in signed], "fp long")
    got = {r.node: r.root for r in simhash.components(simhash.links(d, 2, cap)).collect()}
    classes, mine = {}, {}
    for x, w in zip(signed, want):
        classes.setdefault(w, set()).add(x)
        mine.setdefault(got.get(x, x), set()).add(x)
    assert sorted(map(sorted, classes.values())) == sorted(map(sorted, mine.values()))


def test_every_close_pair_shares_an_anchor():
    rng = np.random.default_rng(4)
    x = rng.integers(0, 2**63, 3000, dtype=np.uint64)
    y = x.copy()
    for k in range(len(y)):
        for b in rng.choice(64, rng.integers(1, 3), replace=False):
            y[k] ^= np.uint64(1 << int(b))
    i, a = simhash.anchors(x)
    j, c = simhash.anchors(y)
    assert len({p for p, _ in set(zip(i.tolist(), a.tolist())) & set(zip(j.tolist(), c.tolist()))}) == len(x)
    assert len(a) / len(x) < 18


def test_near_duplicates_on_a_table(spark, sf):
    d = spark.read.parquet(f"{sf}/documents.parquet")
    got = by_id(queries.op4_simhash_near_duplicates(spark, sf))
    rows = sorted(d.select("doc_id", "text").collect())
    fps = [brute_print(r.text) for r in rows]
    want = brute_components(fps)
    for k, r in enumerate(rows):
        assert got[r.doc_id]["fingerprint"] == f"{fps[k]:016x}"
        assert got[r.doc_id]["component_id"] == rows[want[k]].doc_id


def test_simhash_cases(spark, docs, none):
    got = simhash.near_duplicates(docs).collect()
    assert len(got) == docs.count()
    assert {r.component_id for r in got if r.fp == 0} == {0}
    assert simhash.near_duplicates(none).count() == 0
    kept = simhash.keep_one(docs)
    assert kept.columns == docs.columns
    assert sorted(r.doc_id for r in kept.collect() if r.doc_id is not None)[0] == 0
    assert kept.where("text = 'a b c' OR text = 'A B C'").count() == 1


def test_similar_documents_equal_brute_force(spark, sf):
    rng = random.Random(12)
    rows = [(r.doc_id, r.text) for r in spark.read.parquet(f"{sf}/documents.parquet").select("doc_id", "text").collect()]
    base = [t for _, t in rows if len(t.split()) > 60][:30]
    for k, t in enumerate(base):
        for v in range(3):
            w = t.split()
            for _ in range(max(1, len(w) // (45 + 30 * v))):
                w[rng.randrange(len(w))] = f"edit{rng.randrange(10**6)}"
            rows.append((10_000 + 10 * k + v, " ".join(w)))
    d = spark.createDataFrame(rows, "doc_id long, text string")
    got = {r.doc_id: r.component_id for r in simhash.similar_documents(d).collect()}
    sets = [simhash.shingle_set(simhash.normal_words(t), 5) for _, t in rows]
    root = list(range(len(rows)))

    def find(i):
        while root[i] != i:
            i = root[i]
        return i

    for i in range(len(rows)):
        for j in range(i):
            x, y = sets[i], sets[j]
            if min(len(x), len(y)) >= 0.8 * max(len(x), len(y)) and (not x and not y or len(x & y) >= 0.8 * len(x | y)):
                a, b = sorted((find(i), find(j)))
                root[b] = a
    want = {}
    for i, (k, _) in enumerate(rows):
        want.setdefault(find(i), []).append(k)
    want = {k: min(v) for v in want.values() for k in v}
    assert got == want and sum(k != v for k, v in want.items()) > 40


def test_similar_document_cases(spark, docs, none):
    got = simhash.similar_documents(docs).where("doc_id IS NOT NULL").collect()
    by = {r.doc_id: r.component_id for r in got}
    assert by[0] == by[1] == by[2] == by[3] == 0 and by[8] == by[9] == 8 and by[6] == by[7] == 6
    kept = simhash.keep_similar(docs)
    assert kept.columns == docs.columns and kept.where("doc_id IS NULL").count() == 1
    assert simhash.similar_documents(none).count() == 0 and simhash.keep_similar(none).count() == 0
    assert simhash.keep_similar(docs.limit(1)).count() == 1


# ------------------------------------------------------------------ packing


def test_packing_keeps_every_token(spark, docs):
    path = P.path("byte_bpe_50k.json")
    tok = Tokenizer.from_file(path)
    rng = random.Random(9)
    unspaced = "".join(rng.choices("abcdefghijklmnopqrstuvwxyz", k=30_000))
    odd = ["tail \n x", "a\u2003b <|endoftext|> c", "x" * 9000, "<|endoftext|>", "x<|endoftext|>.,!<|endoftext|>\n<|endo", unspaced, "y" * 150 + "!" * 150, "y" * 150]
    extra = spark.createDataFrame([(100 + i, t) for i, t in enumerate(odd)], "doc_id long, text string")
    d = docs.select("doc_id", "text").where("doc_id IS NOT NULL").dropDuplicates(["doc_id"]).unionByName(extra)
    rows = packing.pack(packing.pieces(d, path, 256), 256).collect()
    texts = {r.doc_id: r.text or "" for r in d.collect()}
    for k, t in texts.items():
        ids = np.array(tok.encode(t, add_special_tokens=False).ids + [0], "<u4")
        mine = sorted((r for r in rows if r.doc_id == k), key=lambda r: r.piece)
        at = 0
        for n, r in enumerate(mine):
            assert (r.piece, r.start) == (n, at) and r.ids_crc32 == zlib.crc32(ids[at : at + r.length].tobytes())
            assert r.length == 256 or n == 0
            at += r.length
        assert at == len(ids)
    seqs = {}
    for r in sorted(rows, key=lambda r: (r.sequence_id, r.offset)):
        assert r.offset == seqs.get(r.sequence_id, 0)
        seqs[r.sequence_id] = r.offset + r.length
    assert max(seqs.values()) <= 256


def slow_sum_of_squares(sizes, capacity):
    gaps, out = [], []
    for s in sizes:
        def cost(g):
            c = [0] * (capacity + 1)
            for x in g:
                if 0 < x:
                    c[x] += 1
            return sum(v * v for v in c)

        options = [(cost([*gaps, capacity - s]), 1, None)]
        for g in sorted({x for x in gaps if x >= s}):
            i = gaps.index(g)
            options.append((cost(gaps[:i] + [g - s] + gaps[i + 1 :]), 0, i))
        best = min(options, key=lambda o: (o[0], o[1]))
        if best[2] is None:
            gaps.append(capacity - s)
        else:
            gaps[best[2]] -= s
        out.append(sum(1 for _ in gaps))
    return len(gaps), out


def test_sum_of_squares_rule():
    rng = random.Random(6)
    for _ in range(60):
        sizes = [rng.randint(1, 12) for _ in range(rng.randint(1, 25))]
        where, offset = packing.sum_of_squares(np.array(sizes), 12)
        bins, opened = slow_sum_of_squares(sizes, 12)
        assert [where[: i + 1].max() + 1 for i in range(len(sizes))] == opened
        fill = {}
        for w, o, s in zip(where, offset, sizes):
            assert o == fill.get(w, 0)
            fill[w] = o + s
        assert max(fill.values()) <= 12 and len(fill) == bins


def test_packing_cases(spark, none, docs):
    path = P.path("byte_bpe_50k.json")
    assert packing.pack(packing.pieces(none, path)).count() == 0
    held = packing.pieces(docs, path, with_ids=True)
    seqs = packing.sequences(packing.pack(held, shard_pieces=5)).collect()
    assert sum(len(r.ids) for r in seqs) == held.agg(F.sum("length")).first()[0]


# ------------------------------------------------------------------ chat


def test_escape_round_trip():
    rng = random.Random(7)
    bits = ["<", "[", "\\", "|turn|>", "/s>", "s>", "INST]", "/INST]", "<SYS>>", "|im_end|>", "x", " "]
    for _ in range(4000):
        t = "".join(rng.choices(bits, k=rng.randint(0, 8)))
        e = chat.escape(t)
        assert chat.unescape(e) == t
        assert not any(c in e for c in chat.TEMPLATE + chat.FOREIGN if c not in ("<|",)), (t, e)


def test_chat_reads_back(spark):
    path = P.path("byte_bpe_50k.tiktoken")
    rows = [(1, 0, "user", "hi </s>"), (1, 1, "assistant", "[INST] ok\n"), (1, 2, "user", None), (1, 3, "assistant", None), (2, 0, None, "x"), (2, 0, "system", "tie"), (None, 0, "assistant", "lost <|end|>"), (3, 1, "assistant", LONG[:5000]), (3, 0, "us<|text|>er", "<|turn|>")]
    c = spark.createDataFrame(rows, "conv_id long, turn long, role string, text string")
    turns = chat.format_turns(c, path, P.PATTERN)
    got = by_id(chat.digest(turns, path, P.PATTERN), "conv_id")
    full = by_id(chat.assemble(turns, path, P.PATTERN), "conv_id")
    for k in (1, 2, None, 3):
        mine = sorted(((r[1], r[2] or "", r[3] or "") for r in rows if r[0] == k))
        said = "".join(t for _, role, t in mine if role == "assistant")
        assert got[k]["n_turns"] == len(mine)
        assert got[k]["turns_sha256"] == hashlib.sha256("".join(f"{r}\n{t}\n" for _, r, t in mine).encode()).hexdigest()
        assert got[k]["loss_chars"] == len(said) and got[k]["loss_sha256"] == hashlib.sha256(said.encode()).hexdigest()
        assert got[k]["formatted_chars"] == len(full[k]["text"]) and len(full[k]["ids"]) == len(full[k]["loss"])
    assert chat.digest(chat.format_turns(c.limit(0), path, P.PATTERN), path, P.PATTERN).count() == 0


# ------------------------------------------------------------------ byte-level BPE


@pytest.fixture(scope="module")
def vocab():
    v = bpe.vocabulary(P.path("byte_bpe_multi_50k.tiktoken"), P.PATTERN)
    return v, tiktoken.Encoding("test", pat_str=P.PATTERN, mergeable_ranks=v.ranks, special_tokens={})


def test_bpe_matches_the_library(vocab):
    v, lib = vocab
    rng = random.Random(9)
    bits = list("aab  \n\n\té1²'st.,!\x85  x") + ["the", "ing", "日本", "😀", "\x1c", "​"]
    texts = ["".join(rng.choices(bits, k=rng.randint(0, 60))) for _ in range(1500)]
    texts += ["a" * 5000, "".join(rng.choices("abcdeéth", k=2000)), LONG]
    for t, ids in zip(texts, v.encode_batch(texts)):
        got = np.frombuffer(ids, "<u4")
        assert got.tolist() == lib.encode_ordinary(t)
        assert v.decode(got) == t.encode()


def test_matrix_and_heap_agree(vocab):
    v, _ = vocab
    rng = random.Random(10)
    words = ["".join(rng.choices("etaoinshrdluéß", k=rng.randint(2, 120))) for _ in range(300)]
    fast = [np.frombuffer(x, "<u4").tolist() for x in v.encode_words(words)]
    slow = [[v.ranks[w.encode()]] if w.encode() in v.ranks else v.merge_long(w.encode()) for w in words]
    assert fast == slow


def test_bpe_cases(spark, docs, none, vocab):
    path = P.path("byte_bpe_multi_50k.tiktoken")
    got = by_id(bpe.digest(docs, path, P.PATTERN))
    assert got[0]["n_tokens"] == 0 and got[0]["ids_sha256"] == hashlib.sha256(b"").hexdigest()
    for i, t in enumerate(TEXTS):
        assert got[i]["decoded_sha256"] == hashlib.sha256((t or "").encode()).hexdigest()
        assert got[i]["n_tokens"] == len(vocab[1].encode_ordinary(t or ""))
    assert bpe.digest(none, path, P.PATTERN).count() == 0
    assert bpe.encode(docs, path, P.PATTERN).columns == [*docs.columns, "ids"]


# ------------------------------------------------------------------ media and counts


def test_media_cases(spark, docs, none):
    got = by_id(webp.digest(docs))
    for i, t in enumerate(TEXTS):
        raw = (t or "").encode()
        padded = raw + b"\xff" * ((-len(raw) % 576) or (0 if raw else 576))
        r = got[i]
        assert r["n_bytes"] == len(raw) and r["payload_sha256"] == hashlib.sha256(padded).hexdigest()
        assert r["tail_crc32"] == zlib.crc32(padded[-32:]) and r["payload_bytes"] == len(padded)
    assert got[8]["media_sha256"] == got[9]["media_sha256"]
    assert webp.digest(none).count() == 0
    stored = webp.store_texts(docs.limit(4))
    px = webp.decode_pixels(stored)
    assert all(r.width == webp.WIDTH == 576 and len(r.argb) == r.width * r.height for r in px.collect())


def test_rollups(spark, docs):
    path, lib = P.path("byte_bpe_50k.json"), Tokenizer.from_file(P.path("byte_bpe_50k.json"))
    counted = token_counts.counted(docs, "byte_bpe_50k", path)
    store = token_counts.Rollup(spark, common.fresh_path(spark, "test-rollup"))
    assert store.totals().count() == 0
    assert store.commit("a", token_counts.signed(counted, 1)) and not store.commit("a", token_counts.signed(counted, 1))
    total = store.totals().collect()
    assert len(total) == 1 and total[0].n_docs == docs.count()
    assert total[0].n_tokens == sum(len(lib.encode(r.text or "", add_special_tokens=False).ids) for r in docs.collect())
    new = token_counts.counted(docs, "ranks", P.path("byte_bpe_50k.tiktoken"), P.PATTERN)
    store.commit("b", token_counts.revised(counted, new))
    assert [r.tokenizer_version for r in store.totals().collect()] == ["ranks"]
    store.commit("c", token_counts.signed(new, -1))
    store.commit("d", token_counts.signed(counted.limit(0), 1))
    assert store.totals().count() == 0 and store.batches() == ["a", "b", "c", "d"]
    with pytest.raises(ValueError):
        store.committed("../x")
    other = token_counts.Rollup(spark, common.fresh_path(spark, "test-rollup"))
    assert store.compact(other, "all") and other.totals().count() == 0


def test_of_two_writers_of_a_batch_one_commits(spark, docs, monkeypatch):
    counted = token_counts.signed(token_counts.counted(docs.limit(3), "v", P.path("byte_bpe_50k.json")), 1)
    store = token_counts.Rollup(spark, common.fresh_path(spark, "test-rollup"))
    monkeypatch.setattr(store, "committed", lambda batch_id: False)  # both looked before either committed
    assert store.commit("a", counted) and not store.commit("a", counted)
    assert store.totals().first().n_docs == 3 and store.batches() == ["a"]


# ------------------------------------------------------------------ pipeline


def test_pipeline_stages(spark, sf):
    import corpus_pipeline as cp

    d = spark.read.parquet(f"{sf}/documents.parquet")
    rows = d
    for name, stage in cp.STAGES[:-1]:
        out = stage(spark, rows, sf)
        assert out.columns == d.columns and dict(out.dtypes) == dict(d.dtypes), name
        path = common.fresh_path(spark, f"test-{name}")
        out.write.parquet(path)
        before, rows = rows.count(), spark.read.parquet(path)
        assert 0 < rows.count() <= before, name
    fps = [brute_print(r.text) for r in rows.collect()]
    assert all(not brute_spans(r.text) for r in rows.collect())
    packed = cp.STAGES[-1][1](spark, rows, sf)
    assert packed.select("doc_id").distinct().count() == rows.count() and len(fps) == rows.count()
    empty = spark.read.parquet(f"{sf}/documents.parquet").limit(0)
    for name, stage in cp.STAGES:
        assert stage(spark, empty, sf).count() == 0, name
