"""Similar documents that meet only where every holder of every shingle is considered."""

import random

from polyedge.llm import simhash


def brute(rows):
    """Smallest id of the component of each row, all pairs compared."""
    sets = [simhash.shingle_set(simhash.normal_words(t), 5) for _, t in rows]
    root = list(range(len(rows)))

    def find(i):
        while root[i] != i:
            i = root[i]
        return i

    for i, x in enumerate(sets):
        for j, y in enumerate(sets[:i]):
            if min(len(x), len(y)) >= 0.8 * max(len(x), len(y)) and len(x & y) >= 0.8 * len(x | y) - 1e-9:
                a, b = sorted((find(i), find(j)))
                root[b] = a
    low = {}
    for i, (k, _) in enumerate(rows):
        low[find(i)] = min(k, low.get(find(i), k))
    return {k: low[find(i)] for i, (k, _) in enumerate(rows)}


def classes(spark, rows):
    return {r.doc_id: r.component_id for r in simhash.similar_documents(spark.createDataFrame(rows, "doc_id long, text string")).collect()}


def test_hub_of_edited_copies(spark):
    rng = random.Random(3)
    base = [f"w{rng.randrange(10**6)}" for _ in range(300)]
    rows = [(250, " ".join(base))]
    for k in [i for i in range(501) if i != 250]:
        w = list(base)
        for at in rng.sample(range(5, 295, 10), 6):
            w[at] = f"edit{rng.randrange(10**9)}"
        rows.append((k, " ".join(w)))
    assert simhash.similarity(rows[1][1], rows[2][1]) < 0.8 < simhash.similarity(rows[0][1], rows[2][1])
    assert set(classes(spark, rows).values()) == {0}


def test_repeats_do_not_hide_a_pair(spark):
    rng = random.Random(4)
    one = [f"w{rng.randrange(10**6)}" for _ in range(300)]
    other = [f"v{rng.randrange(10**6)}" for _ in range(200)]
    line = "read more on page two".split()
    rows = [(1, " ".join(one)), (2, " ".join(one + one)), (3, " ".join(other)), (4, " ".join(other + line * 20))]
    assert classes(spark, rows) == {1: 1, 2: 1, 3: 3, 4: 3} == brute(rows)


def test_one_word_edits_of_short_texts_and_small_vocabularies(spark):
    rng, rows = random.Random(5), []
    for size in range(8, 61):
        for vocabulary in (3, 6, 10**6):
            w = [f"w{rng.randrange(vocabulary)}" for _ in range(size)]
            front, end, swap = list(w), [*w, "added"], list(w)
            front.insert(1, "added")
            swap[size // 2] = "swapped"
            rows += [(len(rows) + k, " ".join(x)) for k, x in enumerate((w, front, end, swap))]
    want = brute(rows)
    assert classes(spark, rows) == want and sum(k != v for k, v in want.items()) > 200


def test_first_keys_of_similar_sets_meet():
    rng = random.Random(6)
    for _ in range(2000):
        x = {rng.getrandbits(64) for _ in range(rng.randrange(1, 80))}
        y = {v for v in x if rng.random() > 0.1} | {rng.getrandbits(64) for _ in range(rng.randrange(0, 6))} or x
        h, g = (simhash.np.array(sorted(v), simhash.np.uint64) for v in (x, y))
        often = simhash.np.array(sorted(rng.sample(sorted(x), len(x) // 2)), simhash.np.uint64)
        frequent = simhash.Frequent(often, simhash.np.arange(len(often)) + 17)
        if len(x & y) >= 0.8 * len(x | y):
            assert set(simhash.first_keys(h, 0.8, frequent)) & set(simhash.first_keys(g, 0.8, frequent))
        assert simhash.np.bitwise_count((simhash.marks(h) ^ simhash.marks(g)).view(simhash.np.uint64)).sum() <= len(x ^ y)


def test_rows_without_an_id_and_repeated_ids(spark):
    rng = random.Random(7)
    a, b, c = (" ".join(f"{p}{rng.randrange(10**6)}" for _ in range(100)) for p in "abc")
    rows = [(1, a), (None, a), (None, a + " more"), (2, b), (2, c), (None, "apart"), (None, "apart")]
    kept = simhash.keep_similar(spark.createDataFrame(rows, "doc_id long, text string"))
    assert sorted((r.doc_id or 0, r.text) for r in kept.collect()) == sorted([(1, a), (2, b), (2, c), (0, "apart")])
