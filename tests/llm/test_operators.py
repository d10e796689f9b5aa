"""Operators against brute force, exact round trips, held-out accuracy and odd inputs."""

import hashlib
import random
import zlib
from collections import Counter
from itertools import combinations

import numpy as np
import pytest
from pyspark.sql import functions as F

from vecspark.llm import chat, decontaminate, html_text, language_id, minhash, mpeg_audio, packing, quality, queries, token_tree, tokens, toxicity

DOCS = "doc_id long, text string, lang string, source string, n_chars long"
ODD = [(1, None, None, None, None), (2, "", "en", "s", 0), (3, " \n\t ", "en", "s", 4), (4, "word " * 3000, "en", "s", 1), (5, "a b c d e f g", "en", "s", 1), (5, "a b c d e f g", "en", "s", 1), (None, "a b c d e f g", "en", "s", 1), (7, "é" * 50, None, "s", 50)]


def odd(spark, rows=ODD):
    return spark.createDataFrame(rows, DOCS).withColumn("score", F.lit("clash")).withColumn("value", F.lit(1))


def shingles(text, width):
    w = (text or "").encode().lower().split()
    return frozenset(tuple(w[i : i + width]) for i in range(max(1, len(w) - width + 1))) if w else frozenset()


def brute_components(rows, width, percent=80):
    sets = {d: shingles(t, width) for d, t in rows}
    parent = {d: d for d in sets}

    def find(x):
        while parent[x] != x:
            x = parent[x]
        return x

    for a, b in combinations(sorted(sets), 2):
        both = len(sets[a] & sets[b])
        if both and 100 * both >= percent * (len(sets[a]) + len(sets[b]) - both):
            u, v = find(a), find(b)
            parent[max(u, v)] = min(u, v)
    return {d: find(d) for d in sets}, {d: len(s) for d, s in sets.items()}


def hot_corpus(seed=5):
    """A large group of near copies at all distances, a passage shared by many, chains and exact copies."""
    rng = random.Random(seed)

    def text(n):
        return [f"w{rng.randint(0, 4000)}" for _ in range(n)]

    base, passage, out = text(150), text(60), []
    for _ in range(220):
        w = list(base)
        for _ in range(rng.randint(0, 9)):
            w[rng.randrange(len(w))] = f"x{rng.randint(0, 10**6)}"
        out.append(w)
    out += [text(rng.randint(0, 80)) + passage + text(rng.randint(5, 60)) for _ in range(120)]
    chain = text(60)
    for i in range(30):
        chain = chain[2:] + text(2)
        out.append(list(chain))
    out += [list(out[3])] * 5 + [text(rng.randint(1, 8)) for _ in range(20)]
    return [(i, " ".join(w)) for i, w in enumerate(out)]


@pytest.mark.parametrize("width", [4, 5])
def test_near_duplicates_are_whole(spark, width):
    rows = hot_corpus()
    want, sizes = brute_components(rows, width)
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    got = {r["doc_id"]: r for r in minhash.near_duplicates(spark, docs, width=width).collect()}
    assert {d: r["component_id"] for d, r in got.items()} == want
    assert all(r["n_shingles"] == sizes[d] and r["kept"] == (want[d] == d) for d, r in got.items())


def test_near_duplicates_odd(spark):
    got = minhash.near_duplicates(spark, odd(spark), width=4).collect()
    assert len(got) == len(ODD)
    by = {r["doc_id"]: r for r in got}
    assert by[1]["n_shingles"] == by[2]["n_shingles"] == by[3]["n_shingles"] == 0 and by[1]["kept"] and by[None]["component_id"] == 5 and not by[None]["kept"]
    assert minhash.near_duplicates(spark, odd(spark).limit(0)).count() == 0


def test_least_overlap():
    assert 20 < minhash.least_overlap(64, 0.8) < 40


def test_packing(spark):
    rows = [(i, "tok " * (37 * i % 5000)) for i in range(60)] + [(61, None)]
    got = packing.pack_documents(spark, spark.createDataFrame(rows, "doc_id long, text string")).collect()
    t = tokens.PieceTokenizer()
    ids = {d: np.append(t.ids(x or ""), 1).astype("<u4") for d, x in rows}
    seqs, pieces = {}, {}
    for r in got:
        assert r["ids_crc32"] == zlib.crc32(ids[r["doc_id"]][r["start"] : r["start"] + r["length"]].tobytes())
        seqs.setdefault(r["sequence_id"], []).append((r["offset"], r["length"]))
        pieces.setdefault(r["doc_id"], []).append((r["start"], r["length"]))
    for parts in pieces.values():
        at = 0
        for start, n in sorted(parts):
            assert start == at
            at += n
    assert {d: sum(n for _, n in p) for d, p in pieces.items()} == {d: len(x) for d, x in ids.items()}
    for parts in seqs.values():
        at = 0
        for offset, n in sorted(parts):
            assert offset == at
            at += n
        assert at == 2048 or at & (at - 1) == 0
    assert packing.pack_documents(spark, odd(spark)).count() >= len(ODD)
    assert packing.pack_documents(spark, odd(spark).limit(0)).count() == 0


@pytest.mark.parametrize("counts", [{1500: 1000, 700: 10}, {2048: 3}, {1: 5000}, {1023: 7, 1025: 5, 3: 2}, {}])
def test_plan_places_everything(counts):
    rows = packing.plan(counts)
    assert sum((hi - lo) * cut for _, lo, hi, _, _, _, cut in rows) == sum(n * c for n, c in counts.items())


def test_closest_fill():
    rng = random.Random(1)
    for _ in range(200):
        items = [rng.randint(1, 30) for _ in range(rng.randint(1, 9))]
        room = rng.randint(1, 60)
        best = max(sum(c) for k in range(len(items) + 1) for c in combinations(items, k) if sum(c) <= room)
        chosen = packing.closest_fill(Counter(items), room)
        assert sum(n * c for n, c in chosen.items()) == best and all(c <= Counter(items)[n] for n, c in chosen.items())


def test_ids_are_those_of_the_json_tokenizer(spark, sf):
    import public_tokenizers
    from tokenizers import Tokenizer

    slow = Tokenizer.from_file(public_tokenizers.path("byte_bpe_50k.json"))
    slow.encode_special_tokens = True
    texts = [r["text"] for r in spark.read.parquet(f"{sf}/documents.parquet").select("text").limit(40).collect()] + ["a  b\n c d <|endoftext|> 's 12é3", " lead", "tail ", "😀 ́x"]
    t = tokens.PieceTokenizer()
    assert [x.ids for x in slow.encode_batch(texts, add_special_tokens=False)] == [t.ids(x).tolist() for x in texts]


def test_added_tokens_are_those_of_the_json_tokenizer(spark):
    import public_tokenizers
    from tokenizers import Tokenizer

    slow, end = Tokenizer.from_file(public_tokenizers.path("byte_bpe_50k.json")), "<|endoftext|>"
    texts = [f"a {end} b", end, f"{end}{end}", f"x  {end}\n\n {end}y <|endof text|>", "plain 12", f" {end} {end}  "]
    want = [x.ids for x in slow.encode_batch(texts, add_special_tokens=False)]
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    t = tokens.PieceTokenizer(added=True)
    assert [t.ids(x).tolist() for x in texts] == want
    assert {r["doc_id"]: r["tokens"][1] for r in token_tree.token_trees(docs).collect()} == {i: len(x) for i, x in enumerate(want)}
    sums = Counter()
    for r in packing.pack_documents(spark, docs).collect():
        sums[r["doc_id"]] += r["length"]
    assert sums == {i: len(x) + 1 for i, x in enumerate(want)}
    rng = random.Random(4)
    for _ in range(200):
        text = "".join(rng.choice(["a", " ", "b\n", end, "<|endof", "text|>"]) for _ in range(rng.choice([1, 9, 300])))
        tree = token_tree.build(t, text)
        tree, text, _ = token_tree.apply_edit(t, tree, text, rng.randint(0, len(text)), rng.choice([0, 1, 9]), rng.choice(["", "x y", end, "text|> "]))
        assert tree.total == len(slow.encode(text, add_special_tokens=False).ids)


def test_token_trees_follow_edits():
    t, rng = tokens.PieceTokenizer(), random.Random(2)
    for _ in range(400):
        text = "".join(rng.choice("ab c\n  é'1.,s ") for _ in range(rng.choice([0, 1, 5, 50, 900])))
        tree = token_tree.build(t, text)
        for _ in range(3):
            tree, text, _ = token_tree.apply_edit(t, tree, text, rng.randint(0, len(text) + 2), rng.choice([0, 1, 5, 100]), "".join(rng.choice("ab \n9.") for _ in range(rng.choice([0, 1, 40]))))
            assert tree.total == t.count(text) and tree.chars[1] == len(text)


def test_token_counts_odd(spark):
    trees = token_tree.token_trees(odd(spark)).withColumn("edits", F.lit(None).cast(f"array<{token_tree.EDIT}>"))
    rows = token_tree.edited_counts(trees).collect()
    assert len(rows) == len(ODD) and all(r["n_tokens"] == r["edited_tokens"] for r in rows)


def test_audio_round_trip():
    rng = random.Random(3)
    for n in (0, 1, 575, 576, 577, 5000, 40000):
        raw = rng.randbytes(n)
        payload = mpeg_audio.payload_of(raw)
        media = mpeg_audio.write_stream(payload, n)
        got = mpeg_audio.read_stream(media)
        assert b"".join(got.main)[: len(payload)] == payload and got.crc_bad == 0 and got.skipped == 0
        assert got.table["frames"] == len(got.offsets) and got.samples == 1152 * len(got.offsets)


def test_audio_damage():
    media = mpeg_audio.write_stream(bytes(range(256)) * 40, 10240)
    whole = mpeg_audio.read_stream(media)
    at = whole.offsets[3]
    torn = mpeg_audio.read_stream(media[:at] + b"junk\xff\xfbjunk" + media[at:])
    assert torn.skipped == 10 and len(torn.offsets) == len(whole.offsets)
    flipped = bytearray(media)
    flipped[at + 8] ^= 1
    assert mpeg_audio.read_stream(bytes(flipped)).crc_bad == 1
    assert mpeg_audio.crc16(b"123456789") == 0xAEE7


def test_media_columns(spark):
    rows = {(r["doc_id"], r["payload_sha256"], r["tail_crc32"], r["n_bytes"]) for r in mpeg_audio.media_columns(odd(spark)).collect()}
    for doc_id, text, *_ in ODD:
        p = mpeg_audio.payload_of((text or "").encode())
        assert (doc_id, hashlib.sha256(p).hexdigest(), zlib.crc32(p[-32:]), len((text or "").encode())) in rows


def test_media_columns_empty_and_features(spark):
    assert mpeg_audio.media_columns(odd(spark).where("false")).count() == 0
    rows = spark.createDataFrame([(1, "same length a"), (2, "same length b"), (3, "same length a")], "doc_id long, text string")
    got = {r["doc_id"]: r for r in mpeg_audio.media_columns(rows).collect()}
    assert got[1]["feature"] == got[3]["feature"] != got[2]["feature"] and all(r["table_agrees"] for r in got.values())


def test_audio_tables_are_held_against_the_frames():
    media = mpeg_audio.write_stream(bytes(range(256)) * 60, 1)
    whole = mpeg_audio.read_stream(media)
    assert mpeg_audio.table_faults(whole) == []
    assert "frames" in mpeg_audio.table_faults(mpeg_audio.read_stream(media[: whole.offsets[-1]]))
    at = media.index(b"Xing")
    bent = bytearray(media)
    bent[at + 16 + 50] ^= 64
    assert mpeg_audio.table_faults(mpeg_audio.read_stream(bytes(bent))) == ["points"]
    head, size = bytes((0xFF, 0xFB, 9 << 4, 0xC4)), 417
    frame = head + bytes(size - 4)
    table = b"VBRI" + bytes(6) + __import__("struct").pack(">IIHHHH", 6 * size, 5, 5, 1, 2, 1) + b"".join(size.to_bytes(2, "big") for _ in range(5))
    stream = head + bytes(32) + table + bytes(size - 36 - len(table)) + frame * 5
    got = mpeg_audio.read_stream(stream)
    assert got.table["kind"] == "VBRI" and got.samples == 5 * 1152 and mpeg_audio.table_faults(got) == []


def bits_crc(bits):
    value = 0xFFFF
    for bit in bits:
        top = value >> 15 ^ bit
        value = value << 1 & 0xFFFF
        value ^= 0x8005 if top else 0
    return value


def test_audio_checksums_of_layers_one_and_two():
    rng = random.Random(8)
    for layer, rate, mode, covered in ((1, 8, 3, lambda b: 128), (1, 8, 0, lambda b: 256), (1, 8, 0x1, lambda b: 4 * (2 * 8 + 24))):
        second = 0xF8 | (4 - layer) << 1
        head = bytes((0xFF, second, rate << 4, mode << 6 | (1 << 4 if mode == 1 else 0)))
        h = mpeg_audio.header_at(head)
        body = rng.randbytes(h.length - 6)
        bits = [int(x) for x in "".join(f"{b:08b}" for b in head[2:] + body)]
        crc = bits_crc(bits[: 16 + covered(body)])
        frame = head + crc.to_bytes(2, "big") + body
        got = mpeg_audio.read_stream(frame * 3)
        assert (got.crc_good, got.crc_bad) == (3, 0)
        bad = bytearray(frame)
        bad[7] ^= 1
        assert mpeg_audio.read_stream(bytes(bad) * 3).crc_bad == 3
    head = bytes((0xFF, 0xFC, 10 << 4, 3 << 6))  # Layer II, mono, 192 kbit/s at 44.1 kHz: thirty subbands
    h = mpeg_audio.header_at(head)
    body = rng.randbytes(h.length - 6)
    bits = [int(x) for x in "".join(f"{b:08b}" for b in body)]
    at = used = 0
    for n in [4] * 11 + [3] * 12 + [2] * 7:
        used += any(bits[at : at + n])
        at += n
    crc = bits_crc([int(x) for x in "".join(f"{b:08b}" for b in head[2:])] + bits[: at + 2 * used])
    got = mpeg_audio.read_stream((head + crc.to_bytes(2, "big") + body) * 2)
    assert (got.crc_good, got.crc_bad) == (2, 0)


def test_audio_tags():
    def tag(version, flags, body, size=mpeg_audio.synchsafe):
        return b"ID3" + bytes((version, 0, flags)) + size(len(body)) + body

    def frame(name, body, size=mpeg_audio.synchsafe):
        return name + size(len(body)) + b"\0\0" + body

    plain = lambda n: n.to_bytes(4, "big")
    cases = [
        (tag(2, 0, b"TT2" + (6).to_bytes(3, "big") + b"\0Title"), {"TIT2": "Title"}),
        (tag(3, 0, frame(b"TIT2", b"\x01" + "Tïtle\0".encode("utf-16"), plain)), {"TIT2": "Tïtle"}),
        (tag(3, 64, plain(6) + bytes(6) + frame(b"TPE1", b"\0Name", plain)), {"TPE1": "Name"}),
        (tag(4, 64, mpeg_audio.synchsafe(6) + b"\1\0" + frame(b"TPE1", b"\x03N\xc3\xa4me")), {"TPE1": "Näme"}),
        (tag(3, 128, frame(b"TXXX", b"\0key\0a\xff\x00\xe0", lambda n: plain(n - 1))), {"key": "a\xff\xe0"}),
        (tag(4, 0, frame(b"APIC", bytes(20)) + frame(b"TXXX", b"\x02" + "k\0v".encode("utf-16-be"))), {"k": "v"}),
    ]
    stream = mpeg_audio.write_stream(b"x" * 576, 576)
    audio = stream[stream.index(b"\xff\xfb") :]
    for raw, want in cases:
        got = mpeg_audio.read_stream(raw + audio)
        assert got.tags == want and got.skipped == 0, (got.tags, want)


PAGE = """<!DOCTYPE html><html><head><title>T</title><style>p{}</style></head><body class="has-sidebar"><header><h1>Site</h1></header>
<nav><ul><li><a href=a>Menu one</a><li><a href=b>Menu two</a></ul></nav><div class="cookie-notice">We use cookies</div><aside>Side text here</aside>
<article><h1>The   title</h1><p>First &amp; long paragraph with many words in it, more than enough.<p>Short.<div class="ad">Buy now</div><form>Name <input></form>
<p>Third&nbsp;paragraph <b>bold</b> text.<br>after break</p><script>var x="</p>";</script><section id="comments"><p>Nice post!</p></section></article><footer>Foot</footer></body></html>"""


def test_html():
    want = "The title\nFirst & long paragraph with many words in it, more than enough.\nShort.\nThird paragraph bold text. after break"
    assert html_text.main_text(PAGE) == want
    assert html_text.main_text(None) == html_text.main_text("") == ""
    assert html_text.main_text("plain text") == "plain text"


def test_html_keeps_all_content():
    long, lead = "Many words of the body text stand here in a row. " * 12, "The lead tells what happened yesterday in the town and why it did. " * 2
    assert html_text.main_text(f"<body><div><div><p>{lead}</div><div><p>{long}<p>{long}</div></div>").split() == (lead + long * 2).split()
    assert html_text.main_text(f"<body><nav>Menu</nav><article><p>{long}<p>{long}</article><article><p>{lead}</article><footer>F</footer>").split() == (long * 2 + lead).split()
    assert html_text.main_text(f"<head><title>T</title></head><body><form><p>{long}</form><script>x()</script>").split() == long.split()
    assert html_text.main_text(f"<body><div><p>{long}<p>{long}</div><article><p>{lead}</article>").split() == (long * 2 + lead).split()
    side = "<div class=sidebar><p>Side words</div>"
    assert html_text.main_text(f"<body><div class='layout with-sidebar'><div><p>{long}</div>{side}</div>").split() == long.split()


def test_html_ratios_decide(spark, sf):
    """Without elements that say what they are, the clustered ratios find most of the given articles;
    with constant ratios none is found."""
    from vecspark.llm.common import table

    right = other = 0
    pages = [r["html"] for r in table(spark, sf, "pages").collect()]
    for html in pages:
        want = html_text.main_text(html)
        bare = html.replace("<article>", "<div>").replace("</article>", "</div>").replace(' class="ad"', "")
        right += html_text.main_text(bare) == want
        other += html_text.main_text(bare, ratio=lambda x: 1.0) == want
    assert right >= 0.8 * len(pages) and other == 0


def test_html_places(spark):
    long, said = "Many words of the body text stand here in a row. " * 12, "I do not agree with a word of what is said up there. " * 6
    page = f"<body><div><a href=1>Home</a> <a href=2>News</a></div><div>Sunny, 20 degrees</div><div><h1>Title</h1><p>{long}</p><p>Short.</p><p>{long}</p></div><div class=comments><p>{said}</p></div><div>Top stories</div></body>"
    assert html_text.main_text(page) == f"Title\n{long.strip()}\nShort.\n{long.strip()}"
    cards = "".join(f"<article class=comment><p>{said}</p></article>" for _ in range(3))
    assert html_text.main_text(f"<body><main><h1>T</h1><div><p>{long}</p></div></main>{cards}") == f"T\n{long.strip()}"
    assert html_text.main_text("<body><div class=ad>Only this</div></body>") == "Only this"
    assert html_text.main_text("<script>x</script>") == "" and html_text.main_text("<p" * 5000) is not None


def test_html_odd(spark):
    rows = [(1, "u", None), (2, None, ""), (None, "v", "<p>a &amp; b"), (4, "w", "<p>" + "long " * 200_000), (4, "w", "<p>x</p>"), (4, "w", "<p>x</p>")]
    pages = spark.createDataFrame(rows, "page_id long, url string, html string").withColumn("text", F.lit("clash")).withColumn("n_chars", F.lit(-1))
    got = html_text.extract_main_text(pages)
    assert got.columns == ["page_id", "url", "text", "n_chars"]
    found = sorted(((r["page_id"], r["url"], r["n_chars"]) for r in got.collect()), key=str)
    assert found == sorted([(1, "u", 0), (2, None, 0), (None, "v", 5), (4, "w", 999_999), (4, "w", 1), (4, "w", 1)], key=str)
    assert html_text.extract_main_text(pages.where("false")).count() == 0


def test_html_pages_keep_their_articles(spark, sf):
    import re

    pages = spark.read.parquet(f"{sf}/pages.parquet")
    html = {r["page_id"]: r["html"] for r in pages.collect()}
    for r in html_text.extract_main_text(pages).collect():
        inner = html[r["page_id"]].split("<article>")[1].split("</article>")[0]
        import html as h

        words = h.unescape(re.sub(r"<[^>]*>", " ", inner)).split()
        assert r["text"].split() == words and r["n_chars"] == len(r["text"])


def test_chat_round_trip(spark):
    rows = [(1, 0, "user", "a & b <s>[x]"), (1, 1, "user", "[+]"), (1, 2, "assistant", "&lt; ok"), (1, 3, None, None), (2, 5, "assistant", ""), (2, 5, "assistant", ""), (None, 0, "ro]le<", "&amp;#91;")]
    f = spark.createDataFrame(rows, "conv_id long, turn long, role string, text string").withColumn("formatted", F.lit(0))
    back = {r["conv_id"]: [(t["role"], t["text"]) for t in r["turns"]] for r in chat.read_back(chat.format_conversations(f)).collect()}
    assert back == {1: [("user", "a & b <s>[x]"), ("user", "[+]"), ("assistant", "&lt; ok"), ("", "")], 2: [("assistant", "")] * 2, None: [("ro]le<", "&amp;#91;")]}
    assert chat.format_conversations(f.limit(0)).count() == 0
    assert "Python" not in chat.digest(chat.loss_mask(chat.read_back(chat.format_conversations(f))))._jdf.queryExecution().executedPlan().toString()


def brute_segments(scores):
    """Maximal segments by their definition: recursive greatest-sum segments."""
    if not len(scores):
        return []
    prefix = np.concatenate(([0.0], np.cumsum(scores)))
    best = max(((prefix[j] - prefix[i], -(j - i), -i, i, j) for i in range(len(scores)) for j in range(i + 1, len(scores) + 1)))
    if best[0] <= 0:
        return []
    i, j = best[3], best[4]
    return brute_segments(scores[:i]) + [(i, j, best[0])] + [(a + j, b + j, v) for a, b, v in brute_segments(scores[j:])]


def test_maximal_segments():
    rng = np.random.default_rng(4)
    for _ in range(300):
        s = rng.normal(-0.2, 1, rng.integers(0, 25))
        got = toxicity.maximal_segments(s)
        assert [(a, b) for a, b, _ in got] == [(a, b) for a, b, _ in brute_segments(s)]


def test_attention_gradient():
    rng = np.random.default_rng(1)
    x, starts, y, w = rng.normal(size=(9, 5)), np.array([0, 4, 6]), np.array([1.0, 0, 1]), np.ones(3)
    model = quality.Attention.fresh(x, 4, 0)

    def loss():
        p = model.forward(x, starts)["p"]
        return -(y * np.log(p) + (1 - y) * np.log(1 - p)).mean()

    g = model.gradient(x, starts, y, w)
    for name, a in model.w.items():
        i = tuple(rng.integers(0, n) for n in a.shape)
        keep = a[i]
        a[i] = keep + 1e-5
        up = loss()
        a[i] = keep - 1e-5
        down = loss()
        a[i] = keep
        assert abs((up - down) / 2e-5 - g[name][i]) < 1e-6


def test_classifiers_hold_out(spark):
    sf = "/root/testdata/sf0.01"
    labels = spark.read.parquet(f"{sf}/labels.parquet")
    for name, target, least in (("op8_toxicity", "toxic", 0.88), ("op10_quality_classifier", "quality", 0.92)):
        got = queries.QUERIES[name](spark, sf).join(labels, "doc_id").where("held_out").select("predicted", target).collect()
        assert np.mean([r[0] == r[1] for r in got]) >= least


def test_quality_trains_on_every_passage(spark, monkeypatch):
    seen = []
    monkeypatch.setattr(quality.Attention, "fit", lambda self, x, starts, y: seen.append(len(x)))
    docs = spark.createDataFrame([(i, "some words here now " * 16 * 40) for i in range(1, 9)], "doc_id long, text string")
    labels = spark.createDataFrame([(i, i % 2, 0) for i in range(1, 9)], "doc_id long, quality int, toxic int")
    quality.train(spark, docs, labels)
    assert seen and seen[0] and seen[0] % 40 == 0
    assert seen[0] == 40 * sum(zlib.crc32(str(i).encode()) % quality.PARTS != quality.HELD for i in range(1, 9))


def test_classifiers_odd(spark):
    labels = spark.createDataFrame([(5, 0, 1), (4, 1, 0), (5, 0, 1), (None, 1, 1), (7, None, None)], "doc_id long, quality int, toxic int")
    for m in (toxicity, quality):
        for lab in (labels, labels.limit(0)):
            model = m.train(spark, odd(spark), lab)
            rows = m.score(odd(spark), model).collect()
            assert len(rows) == len(ODD) and all(0 <= r["score"] <= 1 for r in rows)


def test_common_subsequence():
    rng = random.Random(6)

    def slow(a, b):
        t = [[0] * (len(b) + 1) for _ in range(len(a) + 1)]
        for i, x in enumerate(a):
            for j, y in enumerate(b):
                t[i + 1][j + 1] = t[i][j] + 1 if x == y else max(t[i][j + 1], t[i + 1][j])
        return t[-1][-1]

    for _ in range(200):
        a, b = ([rng.choice("abcd") for _ in range(rng.randint(0, 70))] for _ in range(2))
        assert decontaminate.common_subsequence(a, b) == slow(a, b)


def test_leaks_match_brute_force(spark):
    sf = "/root/testdata/sf0.01"
    docs, items = spark.read.parquet(f"{sf}/documents.parquet"), spark.read.parquet(f"{sf}/benchmark.parquet")
    found = {(r["doc_id"], r["item_id"]) for r in decontaminate.leaks(spark, docs, items).collect()}
    texts = {r["doc_id"]: " ".join((r["text"] or "").split()) for r in docs.collect()}
    want = {(d, r["item_id"]) for r in items.collect() for d, t in texts.items() if " ".join(r["text"].split()) in t}
    assert want <= found and len(found - want) <= 1


def test_leaks_paraphrase_and_odd(spark):
    item = "The quick brown fox jumps over the lazy dog near the quiet river bank today. Its answer is forty two copper coins."
    near = "Intro words come first. The quick red fox jumps over a lazy dog near that quiet river today. Its answer is forty two copper coins. More words follow after it."
    docs = spark.createDataFrame([*ODD, (50, near, "en", "s", 1), (51, item.upper(), "en", "s", 1)], DOCS)
    bench = spark.createDataFrame([(0, item), (1, None), (2, ""), (0, item)], "item_id long, text string")
    got = {(r["doc_id"], r["item_id"]) for r in decontaminate.leaks(spark, docs, bench, common=1.0).collect()}
    assert got == {(50, 0), (51, 0)}
    assert decontaminate.leaks(spark, docs, bench.limit(0)).count() == 0


def test_leaks_in_a_third_of_the_rows(spark):
    """The production defaults where the leaking copies make all of the item's words common."""
    rng = random.Random(8)
    item = " ".join(f"w{rng.randint(0, 400)}" for _ in range(30)) + ". forty two copper coins."
    words = item.split()
    for i in (3, 9, 17):
        words[i] = "other"
    rows = [(i, " ".join(f"v{rng.randint(0, 3000)}" for _ in range(80)) + (f" {' '.join(words)} end" if i % 3 == 0 else "")) for i in range(120)]
    docs, bench = spark.createDataFrame(rows, "doc_id long, text string"), spark.createDataFrame([(0, item)], "item_id long, text string")
    assert {r["doc_id"] for r in decontaminate.leaks(spark, docs, bench).collect()} == {i for i in range(120) if i % 3 == 0}


def test_leaks_at_the_stated_shares_are_all_found(spark):
    """Planted items at 80 % of their words, or at 60 % with the answer whole, in long documents."""
    rng, bench, rows, want = random.Random(9), [], [], set()
    for i in range(60):
        body = [f"w{int(rng.paretovariate(0.6)) % 3000}" for _ in range(rng.randint(12, 45))]
        answer = [f"w{rng.randint(0, 3000)}" for _ in range(3)]
        bench.append((i, " ".join(body) + ". " + " ".join(answer) + "."))
        n = len(body) + 3
        for k, kept in enumerate((n, -(-n * 4 // 5), -(-n * 3 // 5))):
            lost = set(rng.sample(range(len(body)), min(len(body), n - kept)))
            words = [f"z{rng.randint(0, 3000)}" if j in lost else w for j, w in enumerate(body)] + answer
            around = [[f"w{int(rng.paretovariate(0.6)) % 3000}" for _ in range(rng.randint(100, 300))] for _ in range(2)]
            rows.append((i * 3 + k, " ".join(around[0] + words + around[1])))
            want.add((i * 3 + k, i))
    docs, items = spark.createDataFrame(rows, "doc_id long, text string"), spark.createDataFrame(bench, "item_id long, text string")
    got = {(r["doc_id"], r["item_id"]) for r in decontaminate.leaks(spark, docs, items).collect()}
    assert want <= got


def test_leaks_of_long_items_by_paraphrase(spark):
    rng = random.Random(10)
    body = [f"w{rng.randint(0, 900)}" for _ in range(250)]
    item = " ".join(body) + ". forty two copper coins."
    near = [w if i % 3 else "other" for i, w in enumerate(body)]
    rows = [(0, " ".join(near) + ". forty two copper coins"), (1, " ".join(near) + ". nine tin spoons"), (2, " ".join(rng.sample(body, 250)) + ". forty two copper coins")]
    docs, bench = spark.createDataFrame(rows, "doc_id long, text string"), spark.createDataFrame([(0, item)], "item_id long, text string")
    got = decontaminate.leaks(spark, docs, bench).collect()
    assert [(r["doc_id"], r["answered"]) for r in got] == [(0, True)] and got[0]["common"] < 0.8


def test_language(spark, sf):
    docs, pages = spark.read.parquet(f"{sf}/documents.parquet"), spark.read.parquet(f"{sf}/pages.parquet")
    model = language_id.train(spark, docs)
    got = language_id.identify(spark, pages, model).collect()
    assert len(got) == pages.count() and np.mean([r["lang"] == r["declared"] for r in got]) > 0.9
    odd_pages = spark.createDataFrame([(1, None, None), (2, "not a url", ""), (2, "not a url", ""), (3, "http://h.example.de/fr/x", "<html lang=xx>")], "page_id long, url string, html string").withColumn("host", F.lit(3))
    rows = language_id.identify(spark, odd_pages, model).collect()
    assert len(rows) == 4 and all(0 < r["confidence"] <= 1 and r["lang"] in model.langs for r in rows)
    assert language_id.identify(spark, odd_pages.limit(0), model).count() == 0


def test_pipeline(spark):
    import corpus_pipeline as p

    sf = "/root/testdata/sf0.001"
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    assert [n for n, _ in p.STAGES] == ["toxicity", "quality_classifier", "minhash_near_dedup", "benchmark_decontamination", "packing"]
    seen = None
    for name, stage in p.STAGES[:-1]:
        before = {r["doc_id"] for r in docs.select("doc_id").collect()}
        docs = stage(spark, docs, sf)
        assert docs.columns == ["doc_id", "text", "lang", "source", "n_chars"]
        rows = docs.select("doc_id", "text").collect()
        seen = {r["doc_id"] for r in rows}
        assert seen <= before
        if name == "minhash_near_dedup":
            want, _ = brute_components([(r["doc_id"], r["text"]) for r in rows], 5)
            assert all(d == c for d, c in want.items())
    out = p.STAGES[-1][1](spark, docs, sf)
    assert {r["doc_id"] for r in out.select("doc_id").distinct().collect()} == seen
    assert p.drop_near_duplicates(spark, spark.createDataFrame(ODD, DOCS), sf).where("doc_id = 5").count() == 1


def test_pipeline_odd_rows(spark, tmp_path):
    """Nulls, repeated rows, ids shared by different texts, clashing columns and empty tables, stage by stage."""
    import corpus_pipeline as p

    sf = "/root/testdata/sf0.01"
    leak = spark.read.parquet(f"{sf}/benchmark.parquet").where("length(text) > 150").orderBy("item_id").first()["text"]
    toxic = spark.read.parquet(f"{sf}/documents.parquet").join(spark.read.parquet(f"{sf}/labels.parquet").where("toxic = 1"), "doc_id").where("size(array_distinct(split(text, ' '))) > 60").orderBy("n_chars").first()["text"]
    clean = spark.read.parquet(f"{sf}/documents.parquet").join(spark.read.parquet(f"{sf}/labels.parquet").where("toxic = 0 and quality = 1"), "doc_id").orderBy("doc_id").limit(6).collect()
    extra = [(None, leak, "en", "s", 1), (None, clean[0]["text"], "en", "s", 1), (90001, leak, "en", "s", 1), (90001, clean[1]["text"], "en", "s", 1), (90002, clean[2]["text"], "en", "s", 1), (90002, clean[2]["text"], "en", "s", 1), (90003, toxic, "en", "s", 1), (90003, clean[3]["text"], "en", "s", 1), (90004, clean[2]["text"], "en", "s", 1)]
    docs = odd(spark, ODD + extra)

    def texts(frame):
        return Counter((r["doc_id"], r["text"]) for r in frame.collect())

    for name, stage in p.STAGES[:-1]:
        assert stage(spark, docs.where("false"), sf).count() == 0, name
        assert stage(spark, docs, sf).columns == ["doc_id", "text", "lang", "source", "n_chars"]
    assert p.STAGES[-1][1](spark, docs.where("false"), sf).count() == 0
    whole = docs.unionByName(spark.read.parquet(f"{sf}/documents.parquet"), allowMissingColumns=True)  # labelled rows to learn from
    left = texts(p.drop_toxic(spark, whole, sf))
    assert (90003, clean[3]["text"]) in left and (90003, toxic) not in left and left[90002, clean[2]["text"]] == 2
    left = texts(p.drop_poor(spark, whole, sf))
    assert left[90002, clean[2]["text"]] == 2 and (None, clean[0]["text"]) in left
    left = texts(p.drop_near_duplicates(spark, docs, sf))
    assert (90001, leak) in left or (None, leak) in left
    assert sum(n for (_, t), n in left.items() if t == clean[2]["text"]) == 1 and (90001, clean[1]["text"]) in left
    assert sum(n for (_, t), n in left.items() if t == "a b c d e f g") == 1 and left[1, None] == 1
    left = texts(p.drop_leaks(spark, docs, sf))
    assert (90001, leak) not in left and (None, leak) not in left and (90001, clean[1]["text"]) in left and (None, clean[0]["text"]) in left
    packed = p.pack(spark, docs, sf)
    assert packed.agg(F.sum("length")).first()[0] > 0 and packed.where("doc_id is null").count() >= 2


def brute_language(model, pages, trust=4.0, kinship=4.0):
    """Posteriors by plain sums over all pages."""
    import html as entities
    import math
    from urllib.parse import urlsplit

    rows = []
    for page_id, url, page in pages:
        logs, n = model(entities.unescape(language_id.strip(page or "")))
        host = (urlsplit(url or "").hostname or "") if "//" in (url or "") else ""
        hint = (urlsplit(url or "").path.split("/") + ["", ""])[1].lower()
        hint = hint if len(hint) == 2 and hint.isalpha() else ""
        p = np.exp(logs)
        rows.append((page_id, host, ".".join(host.split(".")[-2:]), host.split(".")[-1] + "/" + hint, language_id.declared_language(page or ""), logs, p / p.sum()))
    k, total = len(model.langs), sum(r[6] for r in rows)
    shares = (total + 0.5) / (len(rows) + 0.5 * k)

    def sums(i):
        out = {}
        for r in rows:
            n, s = out.get(r[i], (0, np.zeros(k)))
            out[r[i]] = (n + 1, s + r[6])
        return out

    hosts, domains, kinds, marks = (sums(i) for i in (1, 2, 3, 4))
    got = {}
    for page_id, host, domain, kind, mark, logs, p in rows:
        dn, ds = domains[domain]
        hn, hs = hosts[host]
        prior = (np.maximum(hs - p, 0) + kinship * (ds + kinship * shares) / (dn + kinship)) / (hn - 1 + kinship)
        post = logs + np.log(prior)
        for value, table in ((mark, marks), (kind, kinds)):
            if value or table is kinds:
                n, s = table[value]
                post = post + np.log((s + trust * n / len(rows)) / (total + trust))
        post = np.exp(post - post.max())
        got[page_id] = (model.langs[int(post.argmax())], round(float(post.max() / post.sum()), 5), math.isfinite(float(post.sum())))
    return got


def test_language_is_the_brute_force_fusion(spark):
    from vecspark.llm.common import table

    sf = "/root/testdata/sf0.001"
    model = language_id.train(spark, table(spark, sf, "documents"))
    rows = [(r["page_id"], r["url"], r["html"]) for r in table(spark, sf, "pages").collect()]
    rows += [(900, "http://a.example.com/fr/x", "<html><p></p>"), (901, "http://a.example.com/fr/y", '<html xml:lang="fr"><p>x</p>'), (902, None, None)]
    want = brute_language(model, rows)
    pages = spark.createDataFrame(rows, "page_id long, url string, html string")
    for r in language_id.identify(spark, pages, model).collect():
        lang, confidence, finite = want[r["page_id"]]
        assert finite and r["lang"] == lang and abs(r["confidence"] - confidence) < 1e-4, r


def test_language_of_texts_without_declarations(spark):
    """Held-out documents as pages without a declaration, at addresses that say nothing."""
    from vecspark.llm.common import table

    docs = table(spark, "/root/testdata/sf0.01", "documents").where("lang is not null and length(text) > 40")
    model = language_id.train(spark, docs.where("doc_id % 4 <> 0"))
    held = docs.where("doc_id % 4 = 0")
    pages = held.select(F.col("doc_id").alias("page_id"), F.concat(F.lit("http://h"), F.col("doc_id") % 7, F.lit(".example.com/")).alias("url"), F.concat(F.lit("<html><body><p>"), F.col("text")).alias("html"))
    got = language_id.identify(spark, pages, model).join(held.select(F.col("doc_id").alias("page_id"), F.col("lang").alias("truth")), "page_id")
    row = got.agg(F.count("*").alias("n"), F.count_if(F.col("lang") == F.col("truth")).alias("right")).first()
    assert row["right"] >= 0.97 * row["n"]


def test_language_keys_may_be_hot(spark, monkeypatch):
    """The join that keeps hot keys apart gives the rows of the plain one."""
    left = spark.range(3000).select("id", F.when(F.col("id") % 3 == 0, "hot").otherwise(F.concat(F.lit("k"), F.col("id") % 500)).alias("host"))
    right = left.groupBy("host").agg(F.count("*").alias("rows"), F.max("id").alias("m"))
    want = left.join(right.drop("rows"), "host").select("id", "host", "m").exceptAll
    monkeypatch.setattr(language_id, "SMALL", 10)
    got = language_id.keyed(left, right, "host", 3000).select("id", "host", "m")
    assert got.count() == 3000 and want(got).isEmpty()


def test_language_strip_is_linear():
    import time

    for text in ("<!--" * 100_000, "<script " * 100_000, "<" * 300_000, "<html " * 100_000):
        start = time.perf_counter()
        language_id.strip(text), language_id.declared_language(text)
        assert time.perf_counter() - start < 2
    assert language_id.strip("a<b>c</b><!-- x --><script>y</script>d").split() == ["a", "c", "d"]
