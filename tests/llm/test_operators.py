"""Each operator against brute force on small tables with nulls, empty and long texts, ties, repeated rows, clashing columns."""

import base64
import hashlib
import json
import random
import re
import struct
import zlib
from collections import Counter

import numpy as np
import pytest
from pyspark.sql import functions as F

from rgsketch.llm import language_id, license_scan, media, mixing, secret_scan, sharding, suffix_dedup, url_filter

ODD = [(0, None), (1, ""), (2, "a"), (3, " \t\n"), (4, "x" * 20000), (5, "ünï cödé 漢字 " * 300), (6, "same text"), (7, "same text"), (7, "same text"), (None, "no id"), (None, None), (8, "nul \x00 byte")]


@pytest.fixture(scope="module")
def odd(docs_of):
    """The odd rows with further columns whose names are those of results."""
    extra = ("size", "shard", "slot", "bucket", "rec", "score", "labels", "spans", "media", "key", "cell", "txt", "h", "copies")
    return docs_of(ODD).select("*", *[F.lit(i).alias(c) for i, c in enumerate(extra)])


@pytest.fixture(scope="module")
def none(docs_of):
    return docs_of([])


# --- sharding ----------------------------------------------------------------------------------------------------


def test_shards_hold_every_row_once(spark, odd, none):
    for size in (200, 1 << 20):
        out = sharding.shard(odd, 5, bucket_bytes=size).select("rec.doc_id", "rec.text", "rec.shard", F.col("shard").alias("s"), "slot").collect()
        assert Counter((r[0], r[1]) for r in out) == Counter(ODD)
        counts = Counter(r["s"] for r in out)
        assert max(counts.values()) - min(counts.values()) <= 1
        for s in counts:
            assert sorted(r["slot"] for r in out if r["s"] == s) == list(range(counts[s]))
    assert sharding.shard(none, 5).count() == 0


def test_shuffle_is_reproducible_and_uniform(spark, docs_of):
    rows = [(i, f"text {i}") for i in range(2000)]
    df = docs_of(rows)
    a = {r[0]: r[1] for r in sharding.external_shuffle(df, bucket_bytes=4000).select("rec.doc_id", "rank").collect()}
    b = {r[0]: r[1] for r in sharding.external_shuffle(df.repartition(7), bucket_bytes=4000).select("rec.doc_id", "rank").collect()}
    assert a == b and sorted(a.values()) == list(range(2000))
    assert abs(np.corrcoef(list(a), list(a.values()))[0, 1]) < 0.1


def test_copies_of_a_row_spread(docs_of):
    """Three copies of each row lie about as far apart as rows drawn at random, and keep one slot each."""
    df = docs_of([(i, f"text {i}") for i in range(1500) for _ in range(3)])
    place = {}
    for r in sharding.external_shuffle(df, bucket_bytes=8000).select("rec.doc_id", "rank").collect():
        place.setdefault(r["doc_id"], []).append(r["rank"])
    assert sorted(x for p in place.values() for x in p) == list(range(4500))
    gap = np.mean([max(p) - min(p) for p in place.values()])
    assert 0.46 * 4500 < gap < 0.54 * 4500  # half of all, for three places drawn at random
    hot = docs_of([(1, "same")] * 3000 + [(i, str(i)) for i in range(500)])
    ranks = [r["rank"] for r in sharding.external_shuffle(hot, bucket_bytes=4000).where("rec.doc_id = 1 AND rec.text = 'same'").select("rank").collect()]
    assert abs(np.mean(ranks) - 1750) < 90 and np.std(ranks) > 900


def test_write_shards(spark, docs_of, tmp_path):
    df = docs_of([(i, str(i)) for i in range(20)])
    sharding.write_shards(df, str(tmp_path / "out"), 4)
    got = spark.read.parquet(str(tmp_path / "out"))
    assert got.count() == 20 and got.select("shard").distinct().count() == 4


# --- media -------------------------------------------------------------------------------------------------------


def test_media_round_trip(spark, odd, none):
    out = {(r["doc_id"], r["n_bytes"]): r for r in media.features(media.to_media(odd)).collect()}
    for i, t in ODD:
        data = (t or "").encode()
        padded = data + bytes(-len(data) % 64 or (0 if data else 64))
        r = out[(i, len(data))]
        assert (r["payload_bytes"], r["payload_sha256"], r["tail_crc32"], len(r["hash"])) == (len(padded), hashlib.sha256(padded).hexdigest(), zlib.crc32(padded[-64:]), 8)
    assert media.features(media.to_media(none)).count() == 0


def _filtered(pixels, kinds):
    """A slow encoder of given row filters."""
    out, above = bytearray(), [0] * pixels.shape[1]
    for k, row in zip(kinds, pixels.tolist(), strict=True):
        out.append(k)
        for j, x in enumerate(row):
            a, b, c = (row[j - 1] if j else 0), above[j], (above[j - 1] if j else 0)
            p = a + b - c
            best = min((abs(p - a), 0, a), (abs(p - b), 1, b), (abs(p - c), 2, c))[2]
            out.append((x - (0, a, b, (a + b) >> 1, best)[k]) & 255)
        above = row
    return np.frombuffer(bytes(out), np.uint8).reshape(len(kinds), -1)


def test_all_filters_are_undone():
    rng = np.random.default_rng(1)
    pixels = rng.integers(0, 256, (30, 17), dtype=np.uint8)
    for kinds in (rng.integers(0, 3, 30), rng.integers(0, 5, 30), [2] * 30, [4] * 30, [3] * 30, [1] * 30):
        rows = _filtered(pixels, list(kinds))
        assert (media.unfilter(rows[:, 0], rows[:, 1:]) == pixels).all()


def test_broken_images_are_refused():
    good = media.encode_png(media.payload(b"hello" * 100))
    assert media.decode_png(good).tobytes().startswith(b"hello")
    for at in (3, 20, 60, len(good) - 6):
        with pytest.raises(ValueError):
            media.decode_png(good[:at] + bytes([good[at] ^ 1]) + good[at + 1 :])
    for cut in (0, 10, len(good) - 12):
        with pytest.raises(ValueError):
            media.decode_png(good[:cut])


def test_cosine_hash_of_close_images_is_close():
    rng = np.random.default_rng(2)
    x = np.add.outer(np.arange(200), np.arange(64)).astype(np.float64) / 263 * 200 + rng.normal(0, 10, (200, 64))
    y = x + rng.normal(0, 2, x.shape)
    far = rng.uniform(0, 255, x.shape)
    bits = lambda a: np.unpackbits(np.frombuffer(media.cosine_hash(np.clip(a, 0, 255).astype(np.uint8)), np.uint8))
    assert (bits(x) != bits(y)).sum() < 12 < (bits(x) != bits(far)).sum()


# --- secrets -----------------------------------------------------------------------------------------------------


def _der(tag, body):
    n = len(body)
    size = bytes([n]) if n < 128 else bytes([0x80 | len(b := n.to_bytes((n.bit_length() + 7) // 8, "big"))]) + b
    return bytes([tag]) + size + body


def test_secret_spans():
    rsa = _der(0x30, _der(2, b"\0") + b"".join(_der(2, bytes([1 + i]) * 32) for i in range(8)))
    pkcs8 = _der(0x30, _der(2, b"\0") + _der(0x30, _der(6, b"\x2a\x86\x48")) + _der(4, b"k" * 40))
    ec = _der(0x30, _der(2, b"\1") + _der(4, b"s" * 32))
    part = lambda x: struct.pack(">I", len(x)) + x
    ssh = b"openssh-key-v1\0" + part(b"none") + part(b"none") + part(b"") + struct.pack(">I", 1) + part(b"pub" * 10) + part(b"priv" * 20)
    b64 = lambda x: base64.b64encode(x).decode()
    url = lambda x: base64.urlsafe_b64encode(json.dumps(x).encode()).decode().rstrip("=")
    token = f"{url({'alg': 'HS256', 'typ': 'JWT'})}.{url({'sub': '1'})}.c2lnbmF0dXJl"
    kinds = lambda t: [k for _, _, k in secret_scan.scan(t)]
    for key, kind in ((rsa, "der_key"), (pkcs8, "der_key"), (ec, "der_key"), (ssh, "ssh_key")):
        assert kind in kinds(f"é key {b64(key)} end")
        cut = b64(key[:-3])
        assert kind not in kinds(f"key {cut} end")
    assert "hex_key" in kinds(f"x {rsa.hex()} y") and "hex_key" not in kinds(f"x {rsa.hex()[:-2]} y")
    assert kinds(f"see {token}!") == ["token"]
    assert "token" not in kinds(f"see eyJhbGciOiJub3BlIn0.{'A' * 20}.sig")
    assert kinds("random " + b64(bytes(range(60)))) == []
    text = "é password = 'abc' token: tok3nvalue AKIA" + "A" * 16 + " " + "0af" * 8
    assert secret_scan.scan(text) == [(19, 36, "assign"), (37, 57, "access"), (58, 82, "hex")]


def test_keys_stand_in_any_surroundings():
    part = lambda x: struct.pack(">I", len(x)) + x
    for pad in range(3):
        pkcs8 = _der(0x30, _der(2, b"\0") + _der(0x30, _der(6, b"\x2a\x86\x48")) + _der(4, bytes(range(190, 256)) * 3 + b"k" * pad))
        ssh = b"openssh-key-v1\0" + part(b"none") + part(b"none") + part(b"") + struct.pack(">I", 1) + part(b"pub\xfb\xff" * 10) + part(b"priv" * 20 + b"x" * pad)
        for key, kind in ((pkcs8, "der_key"), (ssh, "ssh_key")):
            std, url = base64.b64encode(key).decode(), base64.urlsafe_b64encode(key).decode()
            assert std != url
            for code in (std, std.rstrip("="), url, url.rstrip("=")):
                lines = [code[i : i + 64] for i in range(0, len(code), 64)]
                if len(lines[-1].rstrip("=")) == 0:
                    continue
                for sep in ("\n", "\r\n", "\n    ", "\n\t", "\\n", "\\r\\n", "\\\\n"):
                    for head, tail in (("", ""), ("key ", " end"), (f"-----BEGIN PRIVATE KEY-----{sep}", f"{sep}-----END PRIVATE KEY-----"), (f"Your key:{sep}", f"{sep}The next word"), ("0f" * 32 + sep, f"{sep}next{sep}more")):
                        for body in (sep.join(lines), code):
                            text = head + body + tail
                            assert (len(head), len(head + body), kind) in secret_scan.confirmed_spans(text), text
                assert secret_scan.confirmed_spans(f"{code[:-8]}\nThe next") == []
    one = base64.b64encode(pkcs8).decode()
    assert [k for _, _, k in secret_scan.confirmed_spans(f"-----BEGIN PRIVATE KEY-----{one}-----END PRIVATE KEY-----")] == ["der_key"]
    assert [k for _, _, k in secret_scan.confirmed_spans(f"{one}\n{one}")].count("der_key") >= 1


def test_secrets_equal_plain_patterns_on_every_row(spark, odd, none, docs_of):
    rng = random.Random(1)
    bits = ["password=", "PASSWD: ", "Token", "api-key", "api_key='", "secret : ", "abc123", "AKIA", "ABCD1234EFGH5678", "deadbeef" * 3, " ", '"', "=", ":", "é", "\n", "token=x", "Kelvin K ſecret=abcdefg"]
    rows = [(i, "".join(rng.choice(bits) for _ in range(rng.randint(0, 30)))) for i in range(300)] + [(900 + k, t) for k, (_, t) in enumerate(ODD)]
    out = {r["doc_id"]: r for r in secret_scan.find_secrets(docs_of(rows)).collect()}
    for i, t in rows:
        want = secret_scan.scan(t)
        r = out[i]
        assert list(zip(r["starts"], r["ends"], r["kinds"], strict=True)) == want
        hexes = [(m.start(), m.end()) for m in re.finditer("[0-9a-f]+", t or "") if len(m[0]) >= 24]
        assert [(s, e) for s, e, k in want if k == "hex"] == hexes
    assert secret_scan.find_secrets(odd).count() == len(ODD) and secret_scan.find_secrets(none).count() == 0


# --- language ----------------------------------------------------------------------------------------------------


def test_language_held_out_accuracy(spark):
    docs = spark.read.parquet("/root/testdata/sf0.01/documents.parquet")
    out = language_id.identify(docs, per_class=60).join(docs.select("doc_id", "lang"), "doc_id").where("held_out")
    r = out.agg(F.avg((F.col("lang") == F.col("lang_pred")).cast("double")).alias("acc"), F.avg("score").alias("score")).first()
    assert r["acc"] > 0.97 and abs(r["score"] - r["acc"]) < 0.08


def test_language_edges(spark, odd, none):
    got = language_id.identify(odd).collect()
    assert len(got) == len(ODD)
    assert {(r["lang_pred"], r["score"]) for r in got if r["doc_id"] in (0, 1, 3)} == {("und", 0.0)}
    assert language_id.identify(none).count() == 0
    no_labels = odd.withColumn("lang", F.lit(None).cast("string"))
    assert {r["lang_pred"] for r in language_id.identify(no_labels).collect()} == {"und"}
    kept = language_id.keep_known(odd)
    assert kept.columns == odd.columns and {r["doc_id"] for r in kept.collect()} >= {6, 7}


def test_counts_of_a_long_text_are_those_of_its_pieces(monkeypatch):
    text = language_id.letters("Some words, and Ünï 漢字 more " * 50)
    whole = language_id.counts(text)
    monkeypatch.setattr(language_id, "PIECE", 37)
    assert (language_id.counts(text) == whole).all()


def test_ftrl_learns_sparse_weights_and_temperature_calibrates():
    rng = np.random.default_rng(0)
    y = rng.integers(0, 3, 600)
    x = [(np.array([c, 10 + rng.integers(50)]), np.array([0.8, 0.6])) for c in y]
    w, b = language_id.fit_ftrl(x, y, 3, l1=0.5)
    z = np.array([v @ w[c] + b for c, v in x])
    assert (z.argmax(1) == y).mean() > 0.98 and (w[70:] == 0).all() and (w[10:60] == 0).mean() > 0.5
    noisy = np.where(rng.random(600) < 0.3, rng.integers(0, 3, 600), y)
    t = language_id.calibrate(20 * np.eye(3)[y], noisy)
    assert t >= 5.0


def test_dsa_and_encrypted_keys():
    """Keys of six numbers, and keys under a password scheme; the same nesting under another identifier is no key."""
    tlv = lambda tag, body: bytes([tag]) + (bytes([len(body)]) if len(body) < 128 else b"\x82" + len(body).to_bytes(2, "big")) + body
    rng = random.Random(6)
    num = lambda n: tlv(2, bytes([rng.randrange(1, 128)]) + rng.randbytes(n - 1))
    dsa = tlv(0x30, tlv(2, b"\0") + num(128) + num(20) + num(128) + num(128) + num(20))
    sealed = lambda oid: tlv(0x30, tlv(0x30, tlv(6, bytes.fromhex(oid)) + tlv(0x30, b"")) + tlv(4, rng.randbytes(200)))
    good, other = sealed("2a864886f70d01050d"), sealed("550406")
    assert secret_scan.is_der_key(dsa) and secret_scan.is_der_key(good) and not secret_scan.is_der_key(other)
    assert not secret_scan.is_der_key(dsa[:-1]) and not secret_scan.is_der_key(tlv(0x30, tlv(2, b"\0") + num(128) + num(20)))


def test_media_null_and_broken(spark):
    good = media.encode_png(media.payload(b"abc"))
    head = good.index(b"IHDR")
    short = good[: head - 4] + media._chunk(b"IHDR", b"abc") + good[head + 4 + 13 + 4 :]
    rows = [(0, 3, good), (1, 0, None), (2, 0, b""), (3, 0, good[:-20]), (4, 0, short), (5, 0, good[:50] + bytes([good[50] ^ 1]) + good[51:])]
    long_data = zlib.compress(bytes(65 * 1000))
    rows.append((6, 0, media.SIGNATURE + media._chunk(b"IHDR", struct.pack(">IIBBBBB", 64, 1, 8, 0, 0, 0, 0)) + media._chunk(b"IDAT", long_data) + media._chunk(b"IEND", b"")))
    got = {r["doc_id"]: r for r in media.features(spark.createDataFrame(rows, "doc_id long, n_bytes long, media binary")).collect()}
    assert got[0]["payload_bytes"] == 64 and got[1]["media_bytes"] is None
    for i in range(2, 7):
        assert got[i]["payload_sha256"] is None and got[i]["media_bytes"] == len(rows[i][2]) and got[i]["media_sha256"] == hashlib.sha256(rows[i][2]).hexdigest()


def test_license_suppression_equals_plain_scan():
    """The kept detections are those that a scan over all kept ones would keep."""
    rng = random.Random(2)
    names = ["licensed under the mit license", "apache license version 2 0", "under the terms of the gnu general public license version 3", "cc by nc 4 0 license", "all rights reserved", "word", "bsd 3 clause license", "permission is hereby granted free of charge to any person obtaining a copy of this software"]
    for _ in range(40):
        text = " ".join(rng.choice(names) for _ in range(rng.randint(1, 25)))
        found = [(r.priority, m.start() - m.end(), order, m.start(), m.end(), r) for order, r in enumerate(license_scan.rules()) if any(k in text for k in r.keywords) for m in r.pattern.finditer(text)]
        kept = []
        for _, _, _, s, e, r in sorted(found, key=lambda f: f[:5]):
            if not any(a <= s and e <= b for a, b, _, _ in kept):
                kept.append((s, e, r.label, r.confidence))
        assert license_scan.detect(text) == sorted(kept)


def test_mix_with_many_sources_and_no_ids(spark):
    """Weights follow the order of sources whatever the ranges; rows without ids are spread by their text."""
    names = sorted({f"s{i * 7919 % 1000:03d}" for i in range(300)})
    src = spark.createDataFrame([(n, f"s{n}", 1) for n in names] + [(None, "n", 1)], "source string, key string, source_size long").repartition(7)
    got = {r["source"]: r["weight"] for r in mixing.cyclic_weights(src).collect()}
    assert got == {n: (5.0, 2.0, 1.0)[i % 3] for i, n in enumerate([*names, None])}
    docs = spark.createDataFrame([(None, f"some words here {i}", "a") for i in range(400)] + [(None, "x y " * 30, "b")] * 40, "doc_id long, text string, source string")
    out = mixing.mix(docs).collect()
    for s in "ab":
        own = [r for r in out if r["source"] == s]
        assert abs(sum(r["taken"] for r in own) - own[0]["target"]) <= 120
    assert mixing.repeat_rows(docs).count() > 0


# --- suffixes ----------------------------------------------------------------------------------------------------


@pytest.mark.parametrize("kind", ["random", "runs", "text", "one"])
def test_suffix_array_is_sorted(kind):
    rng = np.random.default_rng(3)
    data = {"random": rng.integers(0, 256, 500), "runs": np.repeat(rng.integers(97, 100, 60), rng.integers(1, 20, 60)), "text": np.frombuffer(b"banana bandana ananas " * 9, np.uint8), "one": np.full(200, 97)}[kind].astype(np.uint8)
    n = len(data)
    order = suffix_dedup.two_stage_suffix_array(data, n)
    want = sorted(range(n), key=lambda i: data[i:].tobytes())
    assert order.tolist() == want
    assert len(suffix_dedup.two_stage_suffix_array(data[:0], 5)) == 0 and suffix_dedup.two_stage_suffix_array(data[:1], 5).tolist() == [0]


def brute_repeats(rows, length, n_words=50, least=0):
    """n_bytes, n_removed, n_spans, kept_sha256, n_shared of every row, from all strings of all rows."""
    texts = [(t or "").encode() for _, t in rows]
    spans = []
    for b in texts:
        at = [m.span() for m in re.finditer(rb"[^\x00-\x20]+", b)]
        short = [(at[i][0], at[i + n_words - 1][1]) for i in range(len(at) - n_words + 1)]
        spans.append(([(i, i + length) for i in range(len(b) - length + 1)], [(s, e) for s, e in short if least <= e - s < length]))
    places, rows_of = Counter(), [{}, {}]
    for k, (b, both) in enumerate(zip(texts, spans, strict=True)):
        places.update(b[s:e] for s, e in both[0])
        for kind in (0, 1):
            for s, e in both[kind]:
                rows_of[kind].setdefault(b[s:e], set()).add(k)
    out = []
    for b, both in zip(texts, spans, strict=True):
        gone, shared = np.zeros(len(b), bool), np.zeros(len(b), bool)
        for s, e in both[0]:
            if places[b[s:e]] > 1:
                gone[s:e] = True
        for kind in (0, 1):
            for s, e in both[kind]:
                if len(rows_of[kind][b[s:e]]) > 1:
                    shared[s:e] = True
        kept = bytes(x for x, g in zip(b, gone, strict=True) if not g)
        runs = int(gone[0]) + int((gone[1:] & ~gone[:-1]).sum()) if len(b) else 0
        out.append((len(b), int(gone.sum()), runs, hashlib.sha256(kept).hexdigest(), int(shared.sum())))
    return out


def repeats_corpus():
    rng = random.Random(8)
    word = lambda n: "".join(rng.choice("abcdeé ") for _ in range(n))
    shared = [word(60), word(45), "ab" * 40, "z" * 90, word(130)]
    rows = []
    for i in range(120):
        t = "".join(rng.choice([word(rng.randint(0, 30)), rng.choice(shared)]) for _ in range(rng.randint(0, 5)))
        if rng.random() < 0.2 and rows:
            b = list(rng.choice(rows)[1] or "")
            for _ in range(2):
                if b:
                    b[rng.randrange(len(b))] = "q"
            t = "".join(b)
        rows.append((i, t))
    return rows + [(200, None), (201, ""), (202, rows[3][1]), (202, rows[3][1]), (None, rows[5][1]), (None, shared[4]), (203, shared[4][10:])]


@pytest.mark.parametrize("group", [1500, 2, 1])
def test_removed_bytes_equal_brute_force(docs_of, group):
    rows = repeats_corpus()
    out = suffix_dedup.remove_repeats(docs_of(rows), length=40, gram=13, group=group, n_words=6)
    got = Counter((r["doc_id"], r["n_bytes"], r["n_removed"], r["n_spans"], r["kept_sha256"], r["n_shared"]) for r in out.collect())
    assert got == Counter((i, *x) for (i, _), x in zip(rows, brute_repeats(rows, 40, 6, 13), strict=True))


def test_common_prefixes():
    rng = np.random.default_rng(4)
    text = np.concatenate([rng.integers(0, 3, 300), np.tile(rng.integers(0, 256, 30), 4)]).astype(np.uint8)
    order = suffix_dedup.two_stage_suffix_array(text, 50)
    got = suffix_dedup.common_prefixes(suffix_dedup.words_of_eight(text, 50), order, 50)
    padded = [text[i:].tobytes() + bytes(60) for i in order]  # past the end stand zeros
    want = [0] + [min(50, next(k for k in range(61) if k == 60 or a[k] != b[k])) for a, b in zip(padded, padded[1:])]
    assert got.tolist() == want


def test_repeats_of_odd_rows(odd, none):
    got = Counter(tuple(r) for r in suffix_dedup.remove_repeats(odd).collect())
    assert got == Counter((i, *x) for (i, _), x in zip(ODD, brute_repeats(ODD, 400), strict=True))
    assert suffix_dedup.remove_repeats(none).count() == 0


# --- URL filter --------------------------------------------------------------------------------------------------


def test_url_filter_takes_the_entry_in_force(spark):
    day = lambda n: f"2024-01-{n:02d}"
    log = [("bad.com", "block", "add", day(5)), ("bad.com", "block", "remove", day(10)), ("bad.com", "block", "add", day(20)), ("ok.bad.com", "allow", "add", day(6)), ("bad.com", "block", "add", day(5))]
    e = spark.createDataFrame(log, "domain string, list string, action string, day string").withColumn("day", F.col("day").cast("date"))
    caps = [(1, "http://bad.com/x", day(4)), (2, "http://bad.com/x", day(5)), (3, "https://www.bad.com:80/x", day(9)), (4, "http://bad.com", day(10)), (5, "http://user@bad.com/", day(25)), (6, "http://ok.bad.com/", day(25)), (7, None, day(5)), (8, "nonsense", day(5)), (9, "http://notbad.com", day(5)), (9, "http://notbad.com", day(5)), (10, "http://a.ok.bad.com/", day(5)), (11, "http://BAD.com", day(6)), (12, "http://localhost/", day(6)), (13, "http://bad.com", None)]
    c = spark.createDataFrame(caps, "page_id int, url string, day string").withColumn("day", F.col("day").cast("date")).withColumn("host", F.lit("x")).withColumn("verdict", F.lit("y"))
    got = sorted((r["page_id"], r["verdict"]) for r in url_filter.classify(c, e).collect())
    assert got == [(1, "keep"), (2, "block"), (3, "block"), (4, "keep"), (5, "block"), (6, "allow"), (7, "invalid"), (8, "invalid"), (9, "keep"), (9, "keep"), (10, "block"), (11, "block"), (12, "keep"), (13, "keep")]
    assert url_filter.classify(c.limit(0), e).count() == 0 and {r["verdict"] for r in url_filter.classify(c, e.limit(0)).collect()} == {"keep", "invalid"}


def test_url_filter_hosts_and_long_histories(spark):
    """Addresses, dots, slashes; a history of many entries against brute force over all of them."""
    urls = ["http://10.0.0.1/x", "//Bad.com./x", "http://[::1]:80/", "http://[2001:db8::2]/a.b", "http://256.1.2.3.bad.com/"]
    got = [r["h"] for r in spark.createDataFrame([(u,) for u in urls], "u string").select(url_filter.host_of(F.col("u")).alias("h")).collect()]
    assert got == ["10.0.0.1", "bad.com", "[::1]", "[2001:db8::2]", "256.1.2.3.bad.com"]
    parts = [r["s"] for r in spark.createDataFrame([(h,) for h in got], "h string").select(url_filter.suffixes(F.col("h")).alias("s")).collect()]
    assert parts[0] == ["10.0.0.1"] and parts[2] == ["[::1]"] and parts[3] == ["[2001:db8::2]"] and parts[4][-1] == "bad.com"
    rng = random.Random(9)
    names = ["a.com", "x.a.com", "b.org"]
    log = sorted({(rng.choice(names), rng.choice(["block", "allow", "other"]), rng.choice(["add", "remove"]), rng.randrange(1, 300)) for _ in range(150)})
    entries = spark.createDataFrame([(d, l, a, n) for d, l, a, n in log], "domain string, list string, action string, n int").select("domain", "list", "action", F.date_add(F.lit("2024-01-01").cast("date"), F.col("n")).alias("day"))
    caps = [(i, f"http://{rng.choice(['y.x.a.com', 'a.com', 'x.a.com', 'c.b.org'])}/", rng.randrange(0, 310)) for i in range(300)]
    c = spark.createDataFrame(caps, "page_id int, url string, n int").select("page_id", "url", F.date_add(F.lit("2024-01-01").cast("date"), F.col("n")).alias("day"))

    def brute(url, n):
        host = url[7:-1].split(".")
        for i in range(len(host) - 1):
            for name in ("allow", "block"):
                past = [(day, act == "add") for d, l, act, day in log if d == ".".join(host[i:]) and l == name and day <= n]
                if past and max(past)[1]:
                    return name
        return "keep"

    assert {r["page_id"]: r["verdict"] for r in url_filter.classify(c, entries).collect()} == {i: brute(u, n) for i, u, n in caps}


# --- mixing ------------------------------------------------------------------------------------------------------


def fill(sizes, weights, epochs, total):
    target, free = {}, dict(sizes)
    while free:
        left, w = total - sum(target.values()), sum(weights[s] for s in free)
        over = [s for s in free if left * weights[s] / w >= epochs * free[s]]
        if not over:
            return target | {s: left * weights[s] / w for s in free}
        for s in over:
            target[s] = epochs * free.pop(s)
    return target


def test_water_filling_equals_rounds_of_clamping(spark):
    rng = random.Random(3)
    for _ in range(4):
        sizes = {f"s{i}": rng.choice([0, 5, 40, 300, 9000]) for i in range(9)}
        weights = {s: rng.choice([1.0, 2.0, 5.0]) for s in sizes}
        df = spark.createDataFrame([(s, n, weights[s]) for s, n in sizes.items()], "source string, source_size long, weight double")
        got = {r["source"]: r["target"] for r in mixing.water_fill(df, 3).collect()}
        want = fill(sizes, weights, 3, sum(sizes.values()))
        assert all(abs(got[s] - want[s]) < 1e-6 for s in sizes)


def test_mix_comes_near_targets(spark, docs_of, odd, none):
    rng = random.Random(4)
    df = None
    for s, n in (("a", 300), ("b", 40), (None, 500), ("c", 5)):
        part = docs_of([(rng.randrange(10**6), "w " * rng.randint(0, 40)) for _ in range(n)], s)
        df = part if df is None else df.unionByName(part)
    out = mixing.mix(df).collect()
    assert len(out) == 845
    for s in ("a", "b", None, "c"):
        own = [r for r in out if r["source"] == s]
        assert abs(sum(r["taken"] for r in own) - own[0]["target"]) <= 40 and max(r["copies"] for r in own) <= 3
        assert len({r["copies"] for r in own}) <= 2
    assert sorted(map(str, out)) == sorted(map(str, mixing.mix(df.repartition(3)).collect()))
    assert mixing.mix(odd).count() == len(ODD) and mixing.mix(none).count() == 0
    rows = mixing.repeat_rows(df)
    assert rows.columns == df.columns and rows.count() >= sum(r["copies"] for r in out if r["size"])


# --- licenses ----------------------------------------------------------------------------------------------------


def test_license_labels():
    look = lambda t: sorted({x[2] for x in license_scan.detect(" ".join(license_scan.WORD.findall(t.lower())))})
    assert len(license_scan.rules()) > 200
    assert look("Released under the MIT License.") == ["mit"]
    assert look("Licensed under the Apache License, Version 2.0.") == ["apache-2"]
    assert look("This work is licensed under the GNU General Public License, version 3.") == ["gpl-3"]
    assert look("Licensed under CC BY-NC 4.0.") == ["cc-by-nc"]
    assert look("Licensed under CC BY-NC-SA 4.0.") == ["cc-by-nc-sa"]
    assert look("SPDX-License-Identifier: LGPL-2.1-or-later") == ["lgpl-2.1"]
    assert look("Permission is hereby granted, free of charge, to any person obtaining a copy of this software") == ["mit"]
    assert look("the quick brown fox under the tree") == []


def _example(rng, tree):
    """A random string that a parsed pattern matches."""
    out = ""
    for op, arg in tree:
        op = str(op)
        if op == "LITERAL":
            out += chr(arg)
        elif op == "ANY":
            out += rng.choice("ab ")
        elif op == "IN":
            kind, value = rng.choice(arg)
            out += chr(value if str(kind) == "LITERAL" else rng.randint(*value))
        elif op == "MAX_REPEAT":
            out += "".join(_example(rng, arg[2]) for _ in range(rng.randint(arg[0], min(arg[1], 5))))
        elif op == "SUBPATTERN":
            out += _example(rng, arg[3])
        elif op == "BRANCH":
            out += _example(rng, rng.choice(arg[1]))
    return out


def test_gates_lose_no_detection(spark, docs_of, monkeypatch):
    rng = random.Random(6)
    texts = [_example(rng, re._parser.parse(r.pattern.pattern)) for r in license_scan.rules() for _ in range(4)]
    gated = [license_scan.detect(t) for t in texts]
    wrapped = [re.sub(" ", lambda _: rng.choice([" ", "\n", "-", "  "]), t).title() for t in texts]
    rows = {r["doc_id"]: r["labels"] for r in license_scan.scan_licenses(docs_of(list(enumerate(wrapped)))).collect()}
    ungated = [r._replace(keywords=("",)) for r in license_scan.rules()]
    monkeypatch.setattr(license_scan, "rules", lambda: ungated)
    for i, t in enumerate(texts):
        assert gated[i] == license_scan.detect(t) != [], t
        assert {x[2] for x in gated[i]} <= set(rows[i]), wrapped[i]


def test_labels_of_wrapped_and_hyphenated_texts(docs_of):
    cases = [("All rights\nreserved", "proprietary"), ("released into the public\ndomain", "public-domain"), ("placed into the public-domain", "public-domain"), ("All  rights  reserved", "proprietary"), ("This software is provided as-is, without any express or implied warranty. In no event will the authors", "zlib")]
    cases += [(f"licensed under the Creative Commons Attribution Non-Commercial{x} license", f"cc-by-nc{y}") for x, y in (("", ""), ("-ShareAlike", "-sa"), ("-No-Derivatives", "-nd"))] + [("SPDX-License-Identifier: BSL-1.0", "bsl-1")]
    got = {r["doc_id"]: r["labels"] for r in license_scan.scan_licenses(docs_of([(i, t) for i, (t, _) in enumerate(cases)])).collect()}
    assert got == {i: [label] for i, (_, label) in enumerate(cases)}


def test_base_phrases_equal_brute_force(spark, docs_of, odd, none):
    rng = random.Random(5)
    bits = ["under the MIT license", "Apache License, Version 2", "CC-BY-NC", "under", "the", "mit", "cc", "by", "nc", "license", "é", ",", ".", "\n", "2.0", "x"]
    rows = [(i, "".join(rng.choice(bits) + rng.choice([" ", "-", "", "\n"]) for _ in range(rng.randint(0, 25)))) for i in range(300)]
    out = {r["doc_id"]: r for r in license_scan.scan_licenses(docs_of(rows)).collect()}
    phrases = {("under", "the", "mit", "license"): "mit", ("apache", "license", "version", "2"): "apache-2", ("cc", "by", "nc"): "cc-by-nc"}
    for i, t in rows:
        w = re.findall(r"[0-9a-z\x80-\U0010ffff]+", re.sub("[A-Z]", lambda m: m[0].lower(), t))
        at = [(k, lab) for p, lab in phrases.items() for k in range(len(w)) if tuple(w[k : k + len(p)]) == p]
        r = out[i]
        assert (r["n_words"], r["n_base"], r["base_labels"]) == (len(w), len(at), sorted({x for _, x in at}))
        assert (r["first_word"], r["last_word"]) == ((min(at)[0], max(at)[0]) if at else (None, None))
        assert set(r["base_labels"]) <= set(r["labels"]) and 0 <= r["score"] <= 1
    assert license_scan.scan_licenses(odd).count() == len(ODD) and license_scan.scan_licenses(none).count() == 0
