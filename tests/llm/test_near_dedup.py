import random

import numpy as np

from rgsketch.llm import near_dedup as nd
from rgsketch.llm.graph import components


def shingles(text, width):
    w = (text or "").translate(str.maketrans("ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")).split()
    return {tuple(w)} if 0 < len(w) < width else {tuple(w[i : i + width]) for i in range(len(w) - width + 1)}


def brute(rows, width, percent):
    sets = {i: shingles(t, width) for i, t in rows}
    root = {i: i for i in sets}

    def find(i):
        while root[i] != i:
            i = root[i]
        return i

    ids = sorted(sets)
    for k, a in enumerate(ids):
        for b in ids[k + 1 :]:
            common = len(sets[a] & sets[b])
            if common and 100 * common >= percent * len(sets[a] | sets[b]):
                x, y = sorted((find(a), find(b)))
                root[y] = x
    return {i: (len(sets[i]), find(i), find(i) == i) for i in ids}


def corpus(seed=3):
    """Hubs with near and far copies (chains that link off the hub among them), loose texts, short and empty ones."""
    rng = random.Random(seed)
    word = lambda: "".join(rng.choice("abcdefghij") for _ in range(5))

    def change(words, n):
        out = list(words)
        for _ in range(n):
            out[rng.randrange(len(out))] = word()
        return out

    texts = []
    for _ in range(3):
        hub = [word() for _ in range(120)]
        texts.append(hub)
        for _ in range(40):
            texts.append(change(hub, rng.choice([1, 2, 4, 6, 7, 9, 14])))
        far = change(hub, 8)
        for _ in range(4):
            texts.append(change(far, 1))
            far = change(far, 2)
    texts += [[word() for _ in range(rng.randint(1, 60))] for _ in range(40)]
    rows = [" ".join(t) for t in texts] + ["", None, "Solo", "solo", "two words", "TWO  Words\n", "ünï cödé wörds", "é", "x " * 30000]
    rows += [rows[5], rows[5]]
    rng.shuffle(rows)
    return list(enumerate(rows))


def test_components_equal_brute_force(docs_of):
    rows = corpus()
    for width, percent in ((3, 85), (5, 80)):
        got = {r["doc_id"]: (r["n_shingles"], r["component_id"], r["kept"]) for r in nd.NearDuplicates(docs_of(rows), width, percent).groups().collect()}
        assert got == brute(rows, width, percent)


def test_keep_one_keeps_columns_and_one_of_each_group(docs_of):
    rows = corpus(4)
    out = nd.keep_one(docs_of(rows), 3, 85)
    assert out.columns == ["doc_id", "text", "lang", "source", "n_chars"]
    assert sorted(r["doc_id"] for r in out.collect()) == sorted(i for i, v in brute(rows, 3, 85).items() if v[2])


def test_empty_table_and_null_ids(docs_of):
    assert nd.NearDuplicates(docs_of([]), 3, 85).groups().count() == 0
    got = nd.NearDuplicates(docs_of([(None, "a b c d"), (7, "a b c d"), (None, None)]), 3, 85).groups().collect()
    assert sorted((r["doc_id"] or -1, r["component_id"] or -1) for r in got) == [(-1, -1), (-1, 7), (7, 7)]


def test_keep_one_tells_rows_of_one_id_or_none_apart(docs_of):
    rows = [(None, "a b c d e f g"), (None, "h i j k l m n"), (5, "o p q r s t u"), (5, "v w x y z a b"), (6, "O P q r s t u"), (None, "h i j k l m n"), (None, None), (None, None), (5, ""), (5, None)]
    got = sorted(((r["doc_id"] or -1, r["text"] or str(r["text"])) for r in nd.keep_one(docs_of(rows)).collect()))
    assert got == sorted([(-1, "a b c d e f g"), (-1, "h i j k l m n"), (5, "o p q r s t u"), (5, "v w x y z a b"), (-1, "None"), (5, ""), (5, "None")])


def test_registers_merge_and_follow_similarity():
    rng = np.random.default_rng(0)
    base = rng.integers(0, 1 << 63, 3000, dtype=np.uint64)
    a, b = base[:2000], base[500:2500]  # J = 1500 / 2500
    ra, rb, both = nd.registers([a, b, np.union1d(a, b)], 2000)
    assert (np.maximum(ra, rb) == both).all()
    assert abs((ra == rb).mean() - 0.6) < 0.05
    j, top = nd.joint_estimate(np.array([(ra > rb).sum()]), np.array([(ra < rb).sum()]), np.array([(ra == rb).sum()]), np.array([2000.0]), np.array([2000.0]), 0.8)
    assert abs(j[0] - 0.6) < 0.05 and top[0] > 0.6


def test_components_of_long_paths(spark):
    n = 200
    edges = spark.createDataFrame([(i, i + 1) for i in range(n)] + [(1000, 1001)], "a long, b long")
    got = {r["node"]: r["root"] for r in components(edges).collect()}
    assert got == {**{i: 0 for i in range(n + 1)}, 1000: 1000, 1001: 1000}
