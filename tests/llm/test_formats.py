import hashlib
import io
import json
import random
import re
import zlib

import numpy as np
import pytest

from trilist.llm import chat, decontaminate, language, media, tokencount, warc

DOCS = "doc_id long, text string, lang string, source string, doc string"


def docs(spark, rows):
    return spark.createDataFrame([(i, t, "en", "s", "clash") for i, t in rows], DOCS)


def brute_contamination(rows, items, width=10):
    words = lambda t: re.findall(rb"[^\x00-\x2f\x3a-\x60\x7b-\x7f]+", (t or "").encode().lower())
    out = []
    for i, t in rows:
        w, hit, names = words(t), set(), set()
        for name, x in items:
            y = words(x)
            n = min(width, len(y))
            wins = {tuple(y[k : k + n]) for k in range(len(y) - n + 1)} if y else set()
            for p in range(len(w) - n + 1) if y else ():
                if tuple(w[p : p + n]) in wins:
                    hit |= set(range(p, p + n))
                    names.add(str(name))
        out.append((i, len(w), len(hit), sorted(names)))
    return out


@pytest.mark.parametrize("block", [4_000_000, 20])
def test_contamination_equals_brute_force(spark, block):
    r = random.Random(4)
    vocab = "the a of é to in x1 y".split()
    text = lambda n: " ".join(r.choice(vocab) for _ in range(n))
    items = [(i, text(n)) for i, n in enumerate((30, 12, 10, 3, 0, 40))] + [(7, None), (1, text(25))]
    rows = [(i, text(r.randint(0, 80)) + ("" if i % 3 else ", " + items[i % 3][1].upper() + "; end")) for i in range(40)] + [(90, None), (91, ""), (91, "")]
    got = decontaminate.contamination(docs(spark, rows), spark.createDataFrame(items, "item_id long, text string"), block_words=block)
    key = lambda x: (x[0], x[1], x[2], x[3])
    assert sorted(((x.doc.doc_id, x.n_words, x.n_hit, x["items"]) for x in got.collect()), key=key) == sorted(brute_contamination(rows, items), key=key)
    none = decontaminate.contamination(docs(spark, rows), spark.createDataFrame([], "item_id long, text string"))
    assert none.filter("n_hit > 0").count() == 0


def test_longest_matches(spark):
    item = " ".join(f"w{i}" for i in range(30))
    text = "start " + " ".join(f"w{i}" for i in range(5, 25)) + " stop"
    for block in (4_000_000, 5):
        got = decontaminate.longest_matches(docs(spark, [(1, text), (1, text), (2, None), (3, "long " * 300_000 + text)]), spark.createDataFrame([(9, item), (8, "w1 w2")], "item_id long, text string"), block_words=block).collect()
        assert sorted(tuple(x) for x in got) == [(1, "9", 1, 5, 20)] * 2 + [(3, "9", 300_001, 5, 20)]
    assert decontaminate.longest_matches(docs(spark, []), spark.createDataFrame([(9, item)], "item_id long, text string")).count() == 0


def test_language(spark):
    sf = "/root/testdata/sf0.01"
    pred = language.op5_family_svm(spark, sf)
    truth = spark.read.parquet(f"{sf}/documents.parquet").select("doc_id", "lang")
    held = pred.filter("held_out").join(truth, "doc_id").collect()
    assert sum(x.lang == x.lang_pred for x in held) / len(held) > 0.98
    assert all(zlib.crc32(str(x.doc_id).encode()) % 4 == 2 for x in held)
    model = language.train(spark.createDataFrame([("the cat", "en")] * 3, "text string, lang string"))
    assert model.predict("anything") == ("en", 1.0) and model.predict("12 !") == ("und", 0.0) and model.predict(None) == ("und", 0.0)
    assert language.train(spark.createDataFrame([], "text string, lang string")).predict("abc") == ("und", 0.0)


def test_token_cache(spark, tmp_path):
    import public_tokenizers
    import sentencepiece

    rows = [(1, "Hello <s> world"), (2, None), (3, ""), (4, "Hello <s> world"), (5, "word " * 5000), (None, "x")]
    for name in ("piece_bpe_32k.model", "byte_bpe_50k.json", "byte_bpe_50k.tiktoken"):
        cache = str(tmp_path / name)
        got = {(x.doc_id, x.n_tokens) for x in tokencount.count_tokens(docs(spark, rows), name, cache).collect()}
        assert spark.read.parquet(cache).count() == 4
        again = {(x.doc_id, x.n_tokens) for x in tokencount.count_tokens(docs(spark, rows), name, cache).collect()}
        assert again == got and spark.read.parquet(cache).count() == 4
        if name.endswith(".model"):
            sp = sentencepiece.SentencePieceProcessor(model_file=public_tokenizers.path(name))
            assert got == {(i, len(sp.encode(t or ""))) for i, t in rows}


def brute_resize(image, height, width):
    """Each target cell's mean over the area of the samples it covers."""
    h, w = image.shape
    out = np.zeros((height, width))
    for a in range(height):
        for b in range(width):
            for y in range(h):
                for x in range(w):
                    dy = min(y + 1, (a + 1) * h / height) - max(y, a * h / height)
                    dx = min(x + 1, (b + 1) * w / width) - max(x, b * w / width)
                    out[a, b] += max(0, dy) * max(0, dx) * image[y, x]
    return out / (h / height * w / width)


def brute_media(text):
    """What op7 returns of a text, but its feature by brute force."""
    raw = (text or "").encode()
    payload = raw + b"\0" * (max(64, -(-len(raw) // 64) * 64) - len(raw))
    image = np.frombuffer(payload, np.uint8).reshape(-1, 64)
    stored = [media.encode_pgm, media.encode_bmp][zlib.crc32(raw) % 2](image)
    small = np.round(brute_resize(image, 8, 9), 6)
    dhash = "".join("01"[int(v)] for v in (small[:, 1:] > small[:, :-1]).ravel())
    tile = np.round(np.round(brute_resize(image, 16, 16), 6)).astype(np.uint8)
    sha = lambda b: hashlib.sha256(b).hexdigest()
    return len(raw), len(payload), sha(payload), zlib.crc32(payload[-64:]), len(stored), sha(stored), f"{int(dhash, 2):016x}:{sha(media.npy(tile))}"


def test_media_query_equals_brute_force(spark, tmp_path):
    r = random.Random(6)
    texts = [None, "", "x", "x", "é" * 33] + ["".join(r.choice("abc é\n") for _ in range(r.randint(0, 900))) for _ in range(12)]
    docs(spark, list(enumerate(texts))).write.parquet(str(tmp_path / "documents.parquet"))
    got = {x[0]: tuple(x)[1:] for x in media.op7_media_columns(spark, str(tmp_path)).collect()}
    assert got == {i: brute_media(t) for i, t in enumerate(texts)}
    docs(spark, []).write.parquet(str(tmp_path / "none/documents.parquet"))
    assert media.op7_media_columns(spark, str(tmp_path / "none")).count() == 0


def test_media(spark):
    r = np.random.default_rng(0)
    grey, colour = r.integers(0, 256, (7, 13), dtype=np.uint8), r.integers(0, 256, (6, 5, 3), dtype=np.uint8)
    for encode, image in ((media.encode_pgm, grey), (media.encode_bmp, grey), (media.encode_ppm, colour), (media.encode_bmp, colour)):
        assert (media.decode(encode(image)) == image).all()
    assert (media.decode(b"P1\n# c\n3 2\n1 0 1\n0 1 0\n") == np.array([[0, 255, 0], [255, 0, 255]])).all()
    assert (media.decode(b"P4\n3 2\n" + bytes([0b10100000, 0b01000000])) == np.array([[0, 255, 0], [255, 0, 255]])).all()
    assert (media.decode(b"P2 2 1 255 7 9 ") == [[7, 9]]).all()
    big = r.integers(0, 256, (12, 18)).astype(np.uint8)
    assert np.allclose(media.area_resize(big, 4, 6), big.reshape(4, 3, 6, 3).mean((1, 3)))
    assert np.allclose(media.area_resize(big, 5, 7).mean(), big.mean())
    for h, w in ((5, 7), (16, 16), (1, 1), (29, 3)):
        assert np.allclose(media.area_resize(big, h, w), brute_resize(big, h, w))
    assert np.load(io.BytesIO(media.npy(big))).tolist() == big.tolist()
    for bad in (b"GIF89a", b"P5\n9 9\n255\nxx", b"P5\n1 1\n65535\nxx"):
        with pytest.raises(ValueError):
            media.decode(bad)
    rows = [(1, "text é"), (2, None), (3, "a" * 64), (4, "a" * 65), (5, "text é")]
    payloads = docs(spark, rows).selectExpr("doc_id", "CAST(coalesce(text, '') AS BINARY) AS payload")
    for codec in ("pgm", "bmp", "either"):
        got = {x.doc_id: x for x in media.tiles(media.store(payloads, "doc_id", "payload", codec), ["doc_id", "n_bytes"]).collect()}
        for i, t in rows:
            raw = (t or "").encode()
            assert got[i].n_bytes == len(raw) and bytes(got[i].samples) == raw.ljust(max(64, -(-len(raw) // 64) * 64), b"\0")
        assert got[1].dhash == got[5].dhash and bytes(got[1].tile[:6]) == b"\x93NUMPY"


def test_warc_round_trip(spark, tmp_path):
    long = "é" * 60_000 + "\r\n\r\nWARC/1.1 <p>"
    rows = [(1, "http://a/é x", long), (2, None, None), (3, "u", long), (4, "u", "short"), (5, "u", "short"), (None, "u", long), (7, "u", "y" * 100), (7, "u", "y" * 100)]
    pages = spark.createDataFrame([(*r, "extra") for r in rows], "page_id long, url string, html string, digest string")
    warc.write_archives(pages, str(tmp_path / "w"))
    got = warc.read_archives(spark, str(tmp_path / "w")).collect()
    kinds = sorted((x.page_id or "", x.record_type, x.refers_to or "") for x in got)
    assert kinds == sorted([("1", "response", ""), ("2", "response", ""), ("3", "revisit", "1"), ("4", "response", ""), ("5", "response", ""), ("", "revisit", "1"), ("7", "response", ""), ("7", "response", "")])
    for x in got:
        html = next((h or "") for i, _, h in rows if str(i or "") == (x.page_id or ""))
        assert x.digest == hashlib.sha256(html.encode()).hexdigest()
        assert x.record_type == "revisit" or bytes(x.payload) == html.encode()
    warc.write_archives(pages.filter("page_id < 0"), str(tmp_path / "none"))
    assert warc.read_archives(spark, str(tmp_path / "none")).count() == 0
    assert warc.unchunked(b"4;x=1\r\nabcd\r\n0\r\nTrailer: 1\r\n\r\n") == b"abcd"
    with pytest.raises(ValueError):
        list(warc.parse(b"WARC/1.1\r\nContent-Length: 3\r\n\r\nab\r\n\r\n"))


def test_tool_links(spark):
    call = lambda *c: json.dumps({"content": "so", "tool_calls": [{"id": i, "name": n, "arguments": a} for i, n, a in c]})
    result = lambda i: json.dumps({"tool_call_id": i, "content": {"b": 1.0, "a": "é"}})
    ref = lambda i: {"query": {"$result": i}}
    rows = [
        (1, 0, "user", "hi"), (1, 1, "assistant", call(("c2", "search", ref("c1")), ("c1", "search", {"query": "x"}), ("c3", "search", {"limit": 0, "query": "q"}), ("c4", "nope", {}))),
        (1, 2, "tool", result("c1")), (1, 3, "tool", result("c2")), (1, 4, "tool", result("zz")), (1, 5, "assistant", call(("c1", "search", {"query": "again"}))),
        (2, 0, "assistant", call(("x", "search", ref("y")), ("y", "search", ref("x")), ("m", "search", ref("none")))), (2, 1, "user", "{broken"), (None, None, None, None),
    ]
    got = chat.format_chat(spark.createDataFrame([(*r, "z") for r in rows], "conv_id long, turn long, role string, text string, level string")).collect()
    status = {(x.conv_id, x.turn, x.idx): x.status for x in got}
    assert status == {(1, 0, 0): "message", (1, 1, 0): "message", (1, 1, 1): "ok", (1, 1, 2): "ok", (1, 1, 3): "invalid", (1, 1, 4): "unknown_tool", (1, 2, 0): "ok", (1, 3, 0): "ok", (1, 4, 0): "orphan", (1, 5, 0): "message", (1, 5, 1): "duplicate", (2, 0, 0): "message", (2, 0, 1): "cyclic", (2, 0, 2): "cyclic", (2, 0, 3): "missing", (2, 1, 0): "message", (None, None, 0): "message"}
    order = [(x.turn, x.idx) for x in sorted((x for x in got if x.conv_id == 1), key=lambda x: (x.at, x.level, x.turn, x.idx, x.step))]
    assert order.index((1, 2)) < order.index((2, 0)) < order.index((1, 1)) < order.index((3, 0))
    assert next(x.json for x in got if (x.conv_id, x.turn) == (1, 2)) == '{"content":{"a":"é","b":1},"role":"tool","tool_call_id":"c1"}'


def test_legal_json_never_crashes(spark):
    tool = lambda a: '{"tool_calls":[{"id":"i","name":"search","arguments":' + a + "}]}"
    plain = ["1e400", '{"query":"\\ud800"}', "[" * 150 + "]" * 150, "NaN"]
    rows = [(k, 0, "assistant", tool(a)) for k, a in enumerate(plain)] + [(10, 0, "assistant", tool('{"query":"x","limit":' + "9" * 400 + "}")), (11, 0, "assistant", tool('{"query":"' + "é" * 3_000_000 + '"}')), (12, 0, "tool", '{"tool_call_id":"\\udc00"}')]
    schema = "conv_id long, turn long, role string, text string"
    got = {x.conv_id: (x.kind, x.status, x.problem) for x in chat.format_chat(spark.createDataFrame(rows, schema)).collect()}
    assert all(got[k] == ("message", "message", None) for k in (0, 1, 2, 3, 12))
    assert got[10] == ("call", "invalid", "$.limit: out of range") and got[11] == ("call", "unanswered", None)
    assert chat.format_chat(spark.createDataFrame([], schema)).count() == 0


def test_given_conversations_as_calls_reach_every_status(spark):
    done = chat.op3_tool_links(spark, "/root/testdata/sf0.01")
    assert {x.status for x in done.select("status").distinct().collect()} >= {"message", "ok", "orphan", "invalid", "unknown_tool", "missing", "unanswered"}
    assert done.filter("level > 0").count() > 0


def test_language_of_many_copies_is_learned(spark):
    copies = [(f"le chat numero {'abcdefghij'[i % 10]}{'klmno'[i % 5]} dort", "fr") for i in range(10)] * 2000
    rows = spark.createDataFrame(copies + [("the cat sleeps", "en")] * 3, "text string, lang string")
    seen = []
    real, language.Model = language.Model, lambda langs, x: seen.append(list(langs)) or real(langs, x)
    try:
        language.train(rows, 4)
        language.train(rows)
    finally:
        language.Model = real
    assert [sorted(s) for s in seen] == [["en"] + ["fr"] * 4, ["en"] + ["fr"] * 10]
