import random

import numpy as np

from rgsketch.llm import decontaminate as d
from rgsketch.llm.common import utf8
import pyarrow as pa


def levenshtein_part(item, text):
    row = [0] * (len(text) + 1)
    for i, c in enumerate(item, 1):
        new = [i]
        for j, t in enumerate(text, 1):
            new.append(min(row[j] + 1, new[-1] + 1, row[j - 1] + (c != t)))
        row = new
    return min(row)


def random_words(rng, n):
    return " ".join("".join(rng.choice("abcdefghiklmnorstu") for _ in range(rng.randint(2, 9))) for _ in range(n))


def edit(rng, text, share):
    out = []
    for c in text:
        x = rng.random()
        if x < share / 3:
            continue
        out.append(rng.choice("abcxyz") if x < share * 2 / 3 else c)
        if x > 1 - share / 3:
            out.append(rng.choice("abcxyz"))
    return "".join(out)


def test_edits_is_exact():
    rng = random.Random(1)
    for _ in range(100):
        item, text = ("".join(rng.choice("ab c") for _ in range(rng.randint(1, 30))) for _ in range(2))
        assert d.edits(item.encode(), text.encode(), 99) == levenshtein_part(item, text)


def test_recall_against_brute_force():
    rng = random.Random(2)
    items = [random_words(rng, 35) for _ in range(20)]
    index = d.build_index(list(range(20)), items, d.tables_for())
    docs, truth = [], set()
    for k in range(300):
        i, text = rng.randrange(20), f"{random_words(rng, 40)} "
        if k % 3:
            text += edit(rng, items[i], rng.choice([0, 0.03, 0.08, 0.15])) + " "
        docs.append(d.normalise(text + random_words(rng, 30)))
        limit = int(len(items[i]) * 0.2)
        if d.edits(items[i].encode(), docs[-1].encode(), limit) <= limit:
            truth.add((k, i))
    raw, offsets = utf8(pa.array(docs, pa.large_string()))
    got = {(a, b) for a, b, _, _ in d.matches(index, raw, offsets, 0.8)}
    assert got <= truth
    assert len(got) >= 0.97 * len(truth) > 150


def test_embedding_of_equal_strings_is_equal():
    raw = np.frombuffer(b"xxhello worldhello world", np.uint8)
    moves = np.random.default_rng(0).integers(0, 2, (40, 256))
    moves[:, 0] = 0
    out = d.embed(raw, np.array([2, 13]), np.array([13, 24]), moves)
    assert (out[:, 0] == out[:, 1]).all()


def one_typo_a_word(rng, text):
    out = []
    for word in text.split():
        k = rng.randrange(len(word))
        out.append(word[:k] + rng.choice("vwxyz") + word[k + 1 :])
    return " ".join(out)


def test_passages_without_any_surviving_run_are_found():
    rng = random.Random(3)
    items = [random_words(rng, n) for n in (3, 4, 14, 14, 20, 20, 35, 35, 60, 60)]
    assert min(map(len, items)) >= d.RUN_BYTES
    index = d.build_index(list(range(len(items))), items, d.tables_for())
    docs, truth = [], set()
    for k in range(300):
        i = rng.randrange(len(items))
        hurt = one_typo_a_word(rng, items[i]) if k % 3 == 0 else edit(rng, items[i], rng.choice([0.15, 0.17, 0.2]))
        docs.append(d.normalise(f"{random_words(rng, k % 7)} {hurt} {random_words(rng, k % 5)}"))
        for j, item in enumerate(items):
            limit = d.limit_of(item.encode(), 0.8)
            if d.edits(item.encode(), docs[-1].encode(), limit) <= limit:
                truth.add((k, j))
    raw, offsets = utf8(pa.array(docs, pa.large_string()))
    rows = d.matches(index, raw, offsets, 0.8)
    assert {(a, b) for a, b, _, _ in rows} == truth and len(truth) > 150
    for a, b, first, e in rows:
        part = docs[a].encode()[max(0, first - e) : first + len(items[b]) + 2 * e]
        assert d.edits(items[b].encode(), part, e) == e


def test_other_limits_lose_nothing():
    rng = random.Random(4)
    for similarity in (0.6, 0.9, 0.97, 1.0):
        items = [random_words(rng, n) for n in (3, 9, 25, 60)]
        index = d.build_index(list(range(4)), items, d.tables_for(), similarity=similarity)
        docs = [d.normalise(f"{random_words(rng, 3)} {edit(rng, items[k % 4], (1 - similarity) * rng.random())} {random_words(rng, 3)}") for k in range(100)]
        truth = {(k, j) for k, t in enumerate(docs) for j, x in enumerate(items) if d.edits(x.encode(), t.encode(), len(x)) <= d.limit_of(x.encode(), similarity)}
        raw, offsets = utf8(pa.array(docs, pa.large_string()))
        assert {(a, b) for a, b, _, _ in d.matches(index, raw, offsets, similarity)} == truth


def test_scripts_without_blanks_and_dense_edits_equal_brute_force():
    """Unspaced text that stands verbatim or hurt between other characters, and a substituted byte in every eight."""
    rng = random.Random(5)
    han = lambda n: "".join(chr(rng.randrange(0x4E00, 0x4F00)) for _ in range(n))
    items = [han(30), han(45), han(80), random_words(rng, 30)]
    index = d.build_index(list(range(4)), items, d.tables_for())
    docs = [han(20) + items[k % 3] + han(20) for k in range(6)]
    for k in range(60):
        own = list(items[k % 3])
        for at in rng.sample(range(len(own)), int(len(own) * rng.choice([0.05, 0.1, 0.18, 0.25]))):
            own[at] = chr(rng.randrange(0x4E00, 0x4F00))
        docs.append(han(k % 9) + "".join(own) + han(k % 5))
    hurt = list(items[3])
    for at in range(3, len(hurt), 8):
        hurt[at] = "#"
    docs.append(d.normalise(random_words(rng, 5) + " " + "".join(hurt) + " " + random_words(rng, 5)))
    truth = {(k, j) for k, t in enumerate(docs) for j, x in enumerate(items) if d.edits(x.encode(), t.encode(), len(x.encode())) <= d.limit_of(x.encode(), 0.8)}
    raw, offsets = utf8(pa.array(docs, pa.large_string()))
    got = {(a, b) for a, b, _, _ in d.matches(index, raw, offsets, 0.8)}
    assert got == truth and (len(docs) - 1, 3) in truth and {(k, k % 3) for k in range(6)} <= truth


def test_odd_rows_and_tables(spark, docs_of):
    """Nulls, empty and long texts, repeated rows and items, ties, clashing columns, empty tables."""
    rng = random.Random(6)
    passage = random_words(rng, 20)
    long_text = random_words(rng, 4000) + " " + passage.upper() + "  \n" + random_words(rng, 4000)
    rows = [(0, None), (1, ""), (2, "a"), (3, passage), (3, passage), (4, long_text), (None, passage), (5, random_words(rng, 50)), (6, passage + " x " + passage)]
    extra = ("item_id", "edits", "similarity", "start_byte", "spot", "rec", "b")
    docs = docs_of(rows).selectExpr("*", *[f"{i} AS {c}" for i, c in enumerate(extra)])
    items = spark.createDataFrame([(7, passage), (7, passage), (8, None), (9, ""), (10, "short"), (None, passage)], "item_id long, text string").selectExpr("*", "1 AS doc_id", "2 AS lang")
    got = sorted(((r["doc_id"], r["item_id"], r["edits"], r["start_byte"]) for r in d.find_leaks(docs, items).collect()), key=str)
    at = len(d.normalise(long_text[: long_text.index(passage.upper())]).encode()) + 1
    assert got == sorted([(i, j, 0, at if i == 4 else 0) for i in (3, 4, 6, None) for j in (7, None)], key=str)
    kept = d.drop_leaks(docs, items)
    assert kept.columns == docs.columns and sorted(r["doc_id"] for r in kept.collect()) == [0, 1, 2, 5]
    none, empty = docs_of([]), items.where("item_id = 99")
    assert d.find_leaks(none, items).count() == 0 and d.find_leaks(docs, empty).count() == 0 and d.drop_leaks(docs, empty).count() == len(rows)
