"""Main text, language, media, toxicity and decontamination against brute force, with edge rows."""

from __future__ import annotations

import hashlib
import math
import random
import re
import struct
import zlib
from collections import Counter, defaultdict

import pytest
from corpus_rows import prose
from pyspark.sql import functions as F

from tallgram.llm import decontaminate, html_text, language, media, toxicity
from tallgram.llm.common import table

SMALL = "/root/testdata/sf0.01"


def held(doc_id, modulus, remainder):
    return doc_id is not None and zlib.crc32(str(doc_id).encode()) % modulus == remainder


# --- operator 1 ---

PAGE = """<!DOCTYPE html><html><head><title>No</title><style>p{}</style></head><body class="page"><header><h1>Site</h1></header>
<nav><ul><li><a href=/>Home</a></ul></nav><div id="cookie-notice">We use cookies here, as everybody does, and say so at great length to all.</div>
%s<aside>Side text, long enough to look like an article paragraph if nobody knew better, is it not.</aside>
<footer>&copy; nobody</footer></body></html>"""
BODY = """<header><h1>A  title</h1></header><p>First &amp; long paragraph, with <b>bold</b> and&nbsp;more text so that it surges.</p><p>Be.</p><script>var t="</p>";</script>
<!-- <p>hidden</p> --><form><label>Your mail</label><input></form><ul><li>item one<li>item <i>two</i></ul><p>Last &lt;tag&gt; para&eacute;graph.<br>After.<div class="comments"><p>I disagree with all of this, and at length.</p></div>"""
WANT = "A title First & long paragraph, with bold and more text so that it surges. Be. item one item two Last <tag> paraégraph. After."


@pytest.mark.parametrize("box", ["<article>%s</article>", '<main class="x">%s</main>', '<div class="post-content">%s</div>'])
def test_main_text_of_marked_pages(box):
    assert html_text.main_text(PAGE % (box % BODY))[0] == WANT


def test_main_text_by_line_blocks():
    lines = "".join(f"<p>{'Word ' * 12}number {i}.</p>" for i in range(4))
    page = f"<body><div><a href=a>Link one that is long</a></div><div><a href=b>Link two that is long</a></div><h1>Title</h1>{lines}<div><a href=c>More links here</a></div><div><a href=d>And more links here</a></div></body>"
    got, first, last = html_text.main_text(page)
    assert got.startswith("Title Word Word") and got.endswith("number 3.") and "Link" not in got and 0 <= first < last


@pytest.mark.parametrize(("page", "want"), [(None, ""), ("", ""), ("<html></html>", ""), ("plain words", "plain words"), ("<p>a<", "a<"), ("<script>never closed", ""), ("a &am b &amp c", "a &am b & c"), ("<article><p>x<article><p>y</article></article>", "x y"), ("x" * 100_000, "x" * 100_000)])
def test_main_text_edges(page, want):
    assert html_text.main_text(page)[0] == want


def test_main_text_of_given_pages(spark):
    import html

    pages = table(spark, SMALL, "pages")
    got = {r["page_id"]: r for r in html_text.extract_main_text(pages.withColumn("text", F.lit("clash"))).collect()}
    for r in pages.collect():
        inner = re.search(r"<article>(.*)</article>", r["html"], re.S)[1]
        want = " ".join(" ".join(html.unescape(re.sub(r"</?b>", "", x)).split()) for x in re.split(r"</?(?:p|h1|br)>", inner))
        assert got[r["page_id"]]["text"] == " ".join(want.split()) and got[r["page_id"]]["n_chars"] == len(got[r["page_id"]]["text"])


def test_main_text_without_marks_or_names(spark):
    """With every mark, class name and telling element name gone, window sums alone find the article."""
    import html

    wanted = kept = got_all = menus = 0
    for r in table(spark, SMALL, "pages").collect():
        inner = re.search(r"<article>(.*)</article>", r["html"], re.S)[1]
        plain = html.unescape(re.sub(r"<[^>]+>", " ", inner))
        want = Counter(plain.split())
        bare = re.sub(r"</?article>", "", r["html"]).replace(' class="ad"', "")
        bare = re.sub(r"<(/?)(?:nav|footer)>", r"<\1div>", bare)
        text = html_text.main_text(bare)[0]
        got = Counter(text.split())
        wanted, kept, got_all = wanted + sum(want.values()), kept + sum((want & got).values()), got_all + sum(got.values())
        menu = " ".join(html.unescape(x) for x in re.findall(r"<a [^>]*>(.*?)</a>", r["html"]))
        menus += bool(menu) and text.count(menu) > " ".join(plain.split()).count(menu)  # an article may hold the menu's words
    assert kept >= 0.95 * wanted and kept >= 0.95 * got_all and not menus


def test_names_decide_only_what_sums_leave_open():
    body = "".join(f"<p>{'Running text of the body, well over a line. ' * 4}</p>" for _ in range(5))
    for wrong in ("<article>A short teaser, marked.</article><div>%s</div>", '<div class="comments">%s</div><div>Short.</div>', "<aside>%s</aside>"):
        got = html_text.main_text("<body>" + wrong % body + "</body>")[0]
        assert got.startswith("Running text") and got.count("Running text") == 20
    side = "<aside><p>" + "A long text at the side, which surges as well. " * 4 + "</p></aside>"
    for page in (f"<article>{body}</article>{side}", f"<div>{body}</div>{side}"):
        assert "side" not in html_text.main_text(page)[0]


def test_surge_and_dive():
    assert html_text.surge_and_dive([5, 0, 0, 90, 3, 80, 0, 0, 0, 4], [0] * 10) == [(3, 6, 173)]


# --- operator 2 ---


def test_language_edges(edge_docs, no_docs):
    rows = language.identify(edge_docs).collect()
    got = {r["doc_id"]: r for r in rows}
    assert len(rows) == edge_docs.count()
    assert all(got[i]["lang_pred"] == "und" and got[i]["score"] == 0.0 for i in (103, 104, 105))
    assert all(got[i]["lang_pred"] == ("en" if i % 2 else "fr") for i in range(60))
    assert all(0 <= r["score"] <= 1 and r["held_out"] == held(r["doc_id"], 4, 2) for r in rows)
    assert got[100]["score"] == got[101]["score"] == got[109]["score"]
    assert language.identify(no_docs).count() == 0
    kept = language.keep_identified(edge_docs)
    assert kept.columns == edge_docs.columns and kept.count() == edge_docs.count() - 4


def test_language_held_out_accuracy(spark):
    docs = table(spark, SMALL, "documents")
    both = language.identify(docs).join(docs.select("doc_id", "lang", F.length("text").alias("n")), "doc_id").where("held_out and n >= 30")
    assert both.where("lang = lang_pred").count() >= 0.98 * both.count()


def test_language_never_learns_from_held_out_rows(spark):
    """Held-out rows with another label change nothing."""
    docs = table(spark, SMALL, "documents").limit(200).select("doc_id", "text", "lang")
    a = language.identify(docs).collect()
    b = language.identify(docs.withColumn("lang", F.when(language.split_rule(4, 2), "xx").otherwise(F.col("lang")))).collect()
    assert sorted(map(tuple, a), key=str) == sorted(map(tuple, b), key=str)


def test_families():
    assert language.family_of("en") == language.family_of("de") != language.family_of("fr") and language.family_of("zz") == "zz"


# --- operator 3 ---


def test_media_round_trip(edge_docs, edge_rows, no_docs):
    rows = media.media_digests(edge_docs).collect()
    want = defaultdict(list)
    for r in edge_rows:
        raw = (r[1] or "").encode()
        pad = raw + b"\0" * (max(64, -(-len(raw) // 64) * 64) - len(raw))
        want[r[0]].append((len(raw), len(pad), hashlib.sha256(pad).hexdigest(), zlib.crc32(pad[-64:])))
    got = defaultdict(list)
    for r in rows:
        got[r["doc_id"]].append((r["n_bytes"], r["payload_bytes"], r["payload_sha256"], r["tail_crc32"]))
        assert r["declared_ok"] and r["media_bytes"] == r["payload_bytes"] + 44
    assert {k: sorted(v) for k, v in got.items()} == {k: sorted(v) for k, v in want.items()}
    assert media.media_digests(no_docs).count() == 0


def png() -> bytes:
    part = lambda name, data: struct.pack(">I", len(data)) + name + data + struct.pack(">I", zlib.crc32(name + data))
    return b"\x89PNG\r\n\x1a\n" + part(b"IHDR", struct.pack(">IIBBBBB", 1, 1, 8, 0, 0, 0, 0)) + part(b"IDAT", zlib.compress(b"\0\0")) + part(b"IEND", b"")


def test_sniffing_validates_and_carves():
    import gzip

    image, packed = png(), gzip.compress(b"hello", mtime=0)
    value = b"text " + image + b" BM GIF89a RIFF %PDF- " + packed + b" end"
    assert media.carve(value) == [(5, "image/png", image), (len(value) - 4 - len(packed), "application/gzip", packed)]
    assert media.true_type(image, media.sniff(image)) == "image/png"
    assert media.true_type(value, media.sniff(value)) == "application/octet-stream"
    assert media.sniff(image[:-1]) == [] and media.sniff(image[:20] + b"\x01" + image[21:]) == []
    wave = media.wave_of(image)
    assert [k for _, _, k in media.sniff(wave)] == ["audio/wav", "image/png"] and media.wave_samples(wave) == image
    gif = b"GIF89a\x01\0\x01\0\0\0\0,\0\0\0\0\x01\0\x01\0\0\x02\x02D\x01\0;"
    assert media.sniff(gif) == [(0, len(gif), "image/gif")]


def plain_feature(samples, kind, embedded):
    counts = Counter(samples)
    entropy = -sum(n / len(samples) * math.log2(n / len(samples)) for n in counts.values())
    inside = ",".join(f"{t}@{a}+{len(x)}#{zlib.crc32(x):08x}" for a, t, x in embedded)
    return f"type={kind};entropy={abs(entropy):.6f};mean={sum(samples) / len(samples):.6f};zeros={counts[0] / len(samples):.6f};embedded={inside}"


def test_media_feature_equals_a_plain_one(edge_docs, edge_rows):
    want = Counter()
    for r in edge_rows:
        raw = (r[1] or "").encode()
        want[r[0], plain_feature(raw + b"\0" * (max(64, -(-len(raw) // 64) * 64) - len(raw)), "audio/wav", [])] += 1
    assert Counter((r["doc_id"], r["feature"].replace("=-0.0", "=0.0")) for r in media.media_digests(edge_docs).collect()) == want


def test_features_name_embedded_media():
    image = png()
    wave = media.wave_of(b"some" + image + b"more")
    found = media.sniff(wave)
    assert media.feature_of(media.wave_samples(wave), media.true_type(wave, found), media.carve(wave, found)) == plain_feature(b"some" + image + b"more", "audio/wav", [(48, "image/png", image)])


def flac(frames=3, samples=None) -> bytes:
    """Silence, 16 samples a frame: constant subframes."""
    out = b""
    for k in range(frames):
        head = b"\xff\xf8" + bytes([6 << 4 | 9, 0 << 4 | 4 << 1, k, 15])
        check = 0
        for x in head:
            check = media._CRC8[check ^ x]
        body = head + bytes([check]) + b"\0\0\0"
        check = 0
        for x in body:
            check = (check << 8 & 0xFFFF) ^ media._CRC16[(check >> 8) ^ x]
        out += body + struct.pack(">H", check)
    n = 16 * frames if samples is None else samples
    info = struct.pack(">HH", 16, 16) + b"\0" * 6 + ((44100 << 44) | (15 << 36) | n).to_bytes(8, "big") + b"\0" * 16
    return b"fLaC\x80\0\0\x22" + info + out


def test_flac_frames_are_checked():
    whole = flac()
    assert media.sniff(whole + b"rest of the text") == [(0, len(whole), "audio/flac")]
    assert media.sniff(whole[:-1] + b"?") == [] and media.sniff(whole[:50] + b"\x01" + whole[51:]) == []
    assert media.sniff(whole[:42] + b"\xffanything at all") == []
    assert media.sniff(flac(3, 64)) == []  # fewer samples than the head tells
    assert media.sniff(flac(3, 0)) == [(0, len(whole), "audio/flac")]  # unknown number of samples


@pytest.mark.parametrize("piece", [b"\xff\xd8\xff\xe0\0\x04ab\xff\xda\0\x02", b"PK\x03\x04" + b"\0" * 26, b"%PDF-1 ", png()[:33], b"GIF89a" + b"\0" * 7 + b"\x21\xf9\x01a", b"OggS\0" + b"\0" * 22, b"RIFF\xff\xff\0\0WAVE", flac()[:42], b"\x1f\x8b\x08\0" + b"\0" * 14])
def test_validators_take_linear_time(piece):
    import time

    def seconds(n):
        began = time.perf_counter()
        media.sniff(piece * (n // len(piece)))
        return time.perf_counter() - began

    seconds(1 << 14)
    assert min(seconds(1 << 20) for _ in range(2)) < 3.5 * min(seconds(1 << 19) for _ in range(2)) + 0.05


# --- operator 10 ---


def labels(spark, rows):
    return spark.createDataFrame(rows, "doc_id long, quality int, toxic int")


def test_toxicity_learns_words_and_beginnings(spark):
    rows, marks = [], []
    for i in range(400):
        bad = i % 8 == 0
        text = prose(60, i) + ((" plonk" if i % 16 else f" zorg{'abcdefgh'[i // 16 % 8]}ian") if bad else " zone plant")
        rows.append((i, text))
        marks.append((i, 1, int(bad)))
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    out = {r["doc_id"]: r for r in toxicity.toxicity(docs, labels(spark, marks)).collect()}
    assert all(out[i]["predicted"] == int(i % 8 == 0) and out[i]["held_out"] == held(i, 5, 0) for i in out)
    lexicon = toxicity.fit(docs, labels(spark, marks))
    assert lexicon.score("A PL0NK") > 0.5 and lexicon.score("a plonk") > 0.5
    assert lexicon.score("рlоnk thing") > 0.5  # Cyrillic look-alikes
    assert lexicon.score("zorgxxx") > 0.5 > lexicon.score("zone plant")
    # labels of held-out rows change nothing
    flipped = [(i, q, 1 - t if held(i, 5, 0) else t) for i, q, t in marks]
    again = toxicity.fit(docs, labels(spark, flipped))
    assert again.weights == lexicon.weights and again.slope == lexicon.slope


def test_exception_phrases_and_folding():
    lexicon = toxicity.Lexicon({"trash ": 5.0}, ("trash can",), 1.0, -1.0)
    assert lexicon.matches("TR4SH")[2] == [("trash", 5.0)] and lexicon.matches("the trash can")[2] == [] and len(lexicon.matches("trash can trash")[2]) == 1
    assert toxicity.fold("1d10t m0r0n 2020 wow!") == ["idiot", "moron", "2020", "wow"]
    assert lexicon.score(None) == lexicon.score("")
    assert lexicon.feature("trash") > lexicon.feature("trash " + "x " * 5000) > 0


def plain_places(lexicon, words):
    """Every entry tried at every word."""
    phrases = [p.split() for p in lexicon.exceptions]
    free = {k for p in phrases for i in range(len(words)) if words[i : i + len(p)] == p for k in range(i, i + len(p))}
    out = []
    for i, word in enumerate(words):
        hits = [w for e, w in lexicon.weights.items() if (word == e[:-1] if e.endswith(" ") else word.startswith(e))]
        if hits and i not in free:
            out.append((i, max(hits)))
    return out


def test_matches_equal_a_plain_search(spark):

    random.seed(4)
    texts = [r["text"] for r in table(spark, SMALL, "documents").limit(150).collect()] + ["", None, "a", "the the the"]
    vocabulary = sorted({w for t in texts for w in toxicity.fold(t)})
    pairs = [" ".join(w[k : k + 2]) for t in texts for w in [toxicity.fold(t)] for k in range(0, len(w) - 1, 40)]
    weights = {w + " ": random.uniform(-1, 5) for w in random.sample(vocabulary, 40)} | {w[: random.randint(1, 4)]: random.uniform(-1, 5) for w in random.sample(vocabulary, 40)}
    lexicon = toxicity.Lexicon(weights, tuple(sorted(set(random.sample(pairs, 30)))), 0.3, -1.0)
    for t in texts:
        words = toxicity.fold(t)
        want = plain_places(lexicon, words)
        assert lexicon.places(words) == want
        score = 1 / (1 + math.exp(-(0.3 * sum(w for _, w in want) / toxicity.normaliser(len(words)) - 1.0)))
        assert math.isclose(lexicon.score(t), score, rel_tol=1e-9)


def test_folding_equals_plain_replacement(monkeypatch):
    monkeypatch.setattr(toxicity, "FOLDED", 7)
    letters = [*toxicity.LOOKALIKES, *toxicity.SIGNS, *"abZ _-.\t\x1c\u00a0é中😀İß９Ａ"]
    draw = random.Random(5)
    for text in ["", "_", "a_b", *("".join(draw.choices(letters, k=draw.randint(1, 40))) for _ in range(3000)), *("".join(draw.choices("a1b! _\x1c0", k=12)) for _ in range(1000))]:
        plain = "".join(chr(ord(c) - 0xFEE0) if "！" <= c <= "～" else toxicity.LOOKALIKES.get(c, c) for c in text.lower())
        plain = toxicity._SIGNED.sub(lambda m: "".join(toxicity.SIGNS.get(c, c) for c in m[0]), plain)
        assert toxicity.fold(text) == toxicity._WORD.findall(plain), text


def test_clean_counts_equal_plain_ones(spark, monkeypatch):
    """Entries that toxic rows have are counted in full, others at most by a chance hit of the filter."""
    monkeypatch.setattr(toxicity, "COUNTED", 50)
    draw = random.Random(6)
    texts = [" ".join(draw.choices(["scum", "scummy", "house", "garden", "été", "дом", "x"], k=8)) for _ in range(60)]
    rows = spark.createDataFrame([(i, t) for i, t in enumerate(texts)], "doc_id long, text string").repartition(3)
    wanted = ["scum ", "scu", "garden ", "été ", "дом ", "none "]
    got = {r["entry"]: r["clean"] for r in toxicity._clean_counts(rows, spark.createDataFrame([(e,) for e in wanted], "entry string")).collect()}
    want = {e: sum(any((w + " ").startswith(e) and (e.endswith(" ") or w != e) for w in toxicity.fold(t)) for t in texts) for e in wanted[:-1]}
    assert {e: got.get(e, 0) for e in want} == want and got[""] == 60 and "none " not in got and len(got) <= len(want) + 2


def test_exception_phrases_are_learned(spark):
    rows, marks = [], []
    for i in range(600):
        bad, free = i % 6 == 0, i % 24 == 1
        rows.append((i, prose(30, i) + (" plonk " if bad else " plonk bottle " if free else " ") + prose(5, 900 + i)))
        marks.append((i, 1, int(bad)))
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    lexicon = toxicity.fit(docs, labels(spark, marks))
    assert "plonk bottle" in lexicon.exceptions
    assert lexicon.score("a plonk") > 0.5 > lexicon.score("a plonk bottle")


def test_copies_of_one_text_make_no_entry(spark):
    """Equal and near-equal toxic texts have the same neighbours around a rare word."""
    base = prose(40, 5).split()
    copies = [" ".join([*base[:k], *base[k + 1 : 30], "zyxxel", *base[30:]]) for k in range(12)] * 2
    rows = [(i, t) for i, t in enumerate(copies)] + [(100 + i, prose(40, 100 + i) + " plonk " + prose(3, i)) for i in range(40)] + [(200 + i, prose(40, 300 + i)) for i in range(300)]
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    lexicon = toxicity.fit(docs, labels(spark, [(i, 1, int(i < 200)) for i, _ in rows]))
    assert "plonk " in lexicon.weights and not any("zyx" in e for e in lexicon.weights)


def test_held_out_labels_of_the_given_tables(spark):
    """No list of words is shipped: what labels teach finds the toxic rows that were held out."""
    docs, marks = (table(spark, "/root/testdata/sf0.1", n) for n in ("documents", "labels"))
    known = marks.where("toxic is not null").groupBy("doc_id").agg(F.max("toxic").alias("toxic"))
    held_rows = toxicity.scored(docs.where(toxicity.split_rule(5, 0)), toxicity.fit(docs, marks)).join(known, "doc_id").collect()
    hit = sum(r["score"] >= 0.5 and r["toxic"] == 1 for r in held_rows)
    assert hit >= 0.85 * sum(r["toxic"] == 1 for r in held_rows) and hit >= 0.95 * sum(r["score"] >= 0.5 for r in held_rows)


def test_toxicity_edges(spark, edge_docs, no_docs):
    none = labels(spark, [])
    rows = toxicity.toxicity(edge_docs, none).collect()
    assert len(rows) == edge_docs.count() and all(0 <= r["score"] < 0.5 for r in rows)
    odd = labels(spark, [(None, 1, 1), (0, None, None), (1, 1, 1), (1, 1, 1), (2, 1, 0)])
    assert toxicity.toxicity(edge_docs, odd).count() == edge_docs.count()
    assert toxicity.toxicity(no_docs, none).count() == 0
    kept = toxicity.keep_clean(edge_docs, toxicity.Lexicon({"house ": 50.0}))
    assert kept.columns == edge_docs.columns and not kept.where("text rlike '(?i)\\\\bhouse\\\\b'").count()


# --- operator 7 ---

_WORD = re.compile(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+")
_LOWER = str.maketrans("ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")


def words(text):
    return _WORD.findall((text or "").translate(_LOWER))


def brute_contamination(docs, items, window=10):
    at = defaultdict(set)
    for i, t in items:
        w = words(t)
        n = min(window, len(w))
        for k in range(len(w) - n + 1 if n else 0):
            at[tuple(w[k : k + n])].add(i)
    sizes = sorted({len(k) for k in at})
    out = []
    for i, t in docs:
        w, hit, found = words(t), set(), set()
        for n in sizes:
            for k in range(len(w) - n + 1):
                if ids := at.get(tuple(w[k : k + n])):
                    hit.update(range(k, k + n))
                    found |= ids
        out.append((i, len(w), len(hit), len(found), hashlib.sha256(",".join(sorted(map(str, found))).encode()).hexdigest(), bool(hit)))
    return sorted(out, key=str)


def test_contamination_is_exact(spark, edge_docs, edge_rows, monkeypatch):
    base = edge_rows[60][1].split()
    items = [(1, " ".join(base[3:20])), (2, " ".join(base[3:20])), (10, "Stone, LIGHT"), (11, None), (12, "... !"), (13, " ".join(base[-10:]) + " beyond"), (14, "日本語"), (15, "été")]
    benchmark = spark.createDataFrame(items, "item_id long, text string")
    names = ["doc_id", "n_words", "n_hit", "n_items", "items_sha256", "contaminated"]
    want = brute_contamination([(r[0], r[1]) for r in edge_rows], items)
    assert sorted((tuple(r) for r in decontaminate.contamination(edge_docs, benchmark).select(names).collect()), key=str) == want
    kept = decontaminate.keep_uncontaminated(edge_docs, benchmark)
    assert kept.columns == edge_docs.columns and kept.count() == sum(not x[-1] for x in want)
    monkeypatch.setattr(decontaminate, "CHUNK_BYTES", 60)
    chunked = decontaminate.contamination(edge_docs, benchmark)
    assert len(decontaminate.Indexes(benchmark, 10).chunks) > 3
    assert sorted((tuple(r) for r in chunked.select(names).collect()), key=str) == want  # repeated ids and all
    assert decontaminate.keep_uncontaminated(edge_docs, benchmark).count() == kept.count()
    assert "Exchange" not in chunked._jdf.queryExecution().executedPlan().toString()


def test_rows_of_one_id_keep_their_own_hits(spark, monkeypatch):
    """A clean text doesn't inherit what another text of the same id and length hits, however many chunks there are."""
    hit, clean = prose(40, 3), prose(40, 4)
    docs = spark.createDataFrame([(1, hit), (1, clean), (1, hit), (2, clean)], "doc_id long, text string")
    items = [(k, prose(30, 3) if k == 5 else prose(30, 200 + k)) for k in range(12)]
    benchmark = spark.createDataFrame(items, "item_id long, text string")
    names = ["doc_id", "n_words", "n_hit", "n_items", "items_sha256", "contaminated"]
    want = brute_contamination([tuple(r) for r in docs.collect()], items)
    for size in (1 << 20, 100):
        monkeypatch.setattr(decontaminate, "CHUNK_BYTES", size)
        rows = decontaminate.contamination(docs, benchmark).collect()
        assert sorted((tuple(r[n] for n in names) for r in rows), key=str) == want
        assert sorted(r["longest"] for r in rows) == [0, 0, 30, 30]


def test_longest_matches_and_empties(spark, no_docs):
    docs = spark.createDataFrame([(1, "x y " + " ".join(f"w{i}" for i in range(30)) + " z")], "doc_id long, text string")
    items = spark.createDataFrame([(5, "q " + " ".join(f"W{i}" for i in range(4, 25)) + " q")], "item_id long, text string")
    assert [tuple(r) for r in decontaminate.longest_matches(docs, items).collect()] == [(1, "5", 6, 1, 21)]
    none = spark.createDataFrame([], "item_id long, text string")
    assert decontaminate.contamination(docs, none).first()["n_hit"] == 0
    assert decontaminate.contamination(no_docs, items).count() == 0
