"""Each training-data operator against a brute-force version, with nulls, empties, ties, repeats and clashing columns."""

import hashlib
import random
import re
import zlib
from collections import Counter, defaultdict

import duckdb
import numpy as np
import pyarrow as pa
import pytest

from graphweld.llm import html_mincut, iso_media, license_join, mixing, phrase_fingerprint, quality_bayes, queries, simhash_bk, suffix_dedup, token_packing, url_rules

DOCS = "doc_id long, text string, lang string, source string, n_chars long, size int, key string, bucket string, keep string"


def documents(spark, rows):
    """Rows (doc_id, text, source) with extra columns whose names operators use inside."""
    return spark.createDataFrame([(d, t, "en", s, None if t is None else len(t), 7, "k", "b", "x") for d, t, s in rows], DOCS)


@pytest.fixture(scope="module")
def rows():
    r = random.Random(5)
    words = ["alpha", "beta", "Gamma", "déjà", "x", "the", "of", "licensed", "zeta!", "日本", "and", "or"]
    text = lambda n: " ".join(r.choice(words) + r.choice("abcdefgh") for _ in range(n))
    base = [text(120) for _ in range(3)]
    out = [(i, text(r.randint(1, 200)) + (" " + r.choice(base)[r.randint(0, 200) :] if r.random() < 0.4 else ""), r.choice(["a", "a", "a", "b", "c"])) for i in range(80)]
    out += [(100, None, None), (101, "", "b"), (102, "   \n", "c"), (103, out[3][1], "a"), (104, out[3][1], None), (105, "a" * 500, "a"), (106, "ab" * 3000, "b"), (107, text(5000), "z"), (107, "same id", "z"), (108, "w", "q"), (108, "w", "q")]
    return out


def words_of(text):
    return re.findall(r"[^\x20\x09-\x0D]+", text or "")


def test_main_text():
    page = """<html><head><title>T</title><style>p{}</style></head><body><header><p>Top</p></header><nav><a href=x>Home</a></nav>
    <div class="ad">Buy this now, it is good.</div><article><h1>Head &amp; line</h1><p><b>One   two<br>three.<p>Four
    five &#233;.</article><aside>Side words here.</aside><section class="comments"><p>I liked it, really.</p></section><script>var a="<p>x</p>";</script><footer>&copy; foot</footer>"""
    assert html_mincut.main_text(page) == "Head & line One two three. Four five é."
    assert html_mincut.main_text(None) == html_mincut.main_text("") == html_mincut.main_text("<p") == ""
    assert html_mincut.main_text("<article><p>cut off &am</p><p>here <b") == "cut off &am here"


def test_raw_elements_end_at_their_end_tag():
    body = "<article><p>The text of it, all of it.</p></article>"
    for script in ("<script>for(i=0;i<n;i++)f()</script>", "<SCRIPT>a<b</Script >", "<style>a<b</style>", "<title>x<y 'z</title>"):
        assert html_mincut.main_text(script + body + "<script>1</script>") == "The text of it, all of it."
    assert html_mincut.main_text("<article><p>Let <math><mi>x</mi></math> be, <svg><path d='1'/><text>five</text></svg> or <button>six</button>.</p></article>") == "Let x be, five or six."
    assert html_mincut.main_text(body + "<script>if(a<b)") == "The text of it, all of it."
    two = "<article><p>First words of it, here.</p>{}<p>Then the others, there.</p></article>"
    for script in ("<script>document.write(\"<a href='x'+y);</script>", '<script>var s="<!--";</script>'):
        assert html_mincut.main_text(two.format(script)) == "First words of it, here. Then the others, there."
    for tag, text in (('<p title="A hidden gem">', "Kept."), ('<p data-id="comments">', "Kept."), ("<p><a href=/x?id=nav>", "Kept.")):
        assert html_mincut.main_text(two.format(f"{tag}{text}</p>")) == f"First words of it, here. {text} Then the others, there."


def test_the_cut_decides():
    long = "<p>A long enough paragraph, with words and stops in it. And then some more of them, to be sure.</p>"
    alone = lambda page: [k for _, k in html_mincut.labelled(page, smooth=0)]
    cut = lambda page: [k for _, k in html_mincut.labelled(page)]
    between = f"<body><div>{long}<div>Short bit</div>{long}</div></body>"
    assert alone(between) == [True, False, True] and cut(between) == [True, True, True]
    at_the_end = f"<body><div>{long}{long}<div>Short bit</div></div></body>"
    assert alone(at_the_end) == cut(at_the_end) == [True, True, False]


def test_minimum_cut_is_the_cheapest_labelling():
    r = random.Random(1)
    for _ in range(60):
        n = r.randint(1, 7)
        a, b = [r.random() * 3 for _ in range(n)], [r.random() * 3 for _ in range(n)]
        edges = {(i, j): r.random() for i in range(n) for j in range(i + 1, n) if r.random() < 0.5}
        cost = lambda keep: sum(b[i] if keep[i] else a[i] for i in range(n)) + sum(c for (i, j), c in edges.items() if keep[i] != keep[j])  # noqa: E731, B023
        best = min(cost([bool(m >> i & 1) for i in range(n)]) for m in range(1 << n))
        assert abs(cost(html_mincut.minimum_cut(a, b, edges)) - best) < 1e-6


def test_main_text_query(spark):
    pages = spark.createDataFrame([(1, "u", None, "x"), (2, None, "<p>Hello there, you.</p>", "y"), (3, "v", "", "z")], "page_id long, url string, html string, text string")
    assert {(r.page_id, r.text, r.n_chars) for r in html_mincut.extract(pages).collect()} == {(1, "", 0), (2, "Hello there, you.", 17), (3, "", 0)}
    assert html_mincut.extract(pages.limit(0)).count() == 0


def test_mixing(spark, rows):
    got = mixing.mix(documents(spark, rows)).collect()
    size = Counter()
    for _, t, s in rows:
        size[s] += len(words_of(t))
    order = sorted(size, key=lambda s: (s is None, (s or "").encode()))
    weight = dict(zip(order, [1.0, 2.0, 3.0] * 9, strict=False))
    full: set = set()
    while True:
        left = sum(size.values()) - sum(3 * size[s] for s in full)
        open_weight = sum(weight[s] for s in order if s not in full)
        target = {s: 3.0 * size[s] if s in full else left * weight[s] / open_weight for s in order}
        above = {s for s in order if target[s] > 3 * size[s] + 1e-9} - full
        if not above:
            break
        full |= above
    assert Counter((r.doc_id, r["size"]) for r in got) == Counter((d, len(words_of(t))) for d, t, _ in rows)
    assert full
    taken = Counter()
    by_size = {v: s for s, v in size.items()}
    for r in got:
        s = by_size[r.source_size]
        assert abs(r.target - target[s]) < 1e-6 * max(1, target[s]) and 0 <= r.taken <= 3 * r["size"]
        taken[s] += r.taken
    assert all(abs(taken[s] - target[s]) <= 0.5 + 1e-6 for s in order)
    assert sorted(map(tuple, mixing.mix(documents(spark, rows)).drop("mix_key").collect())) == sorted(tuple(r)[:1] + tuple(r)[2:] for r in got)
    assert mixing.mix(documents(spark, [])).count() == 0
    whole = mixing.mixed_documents(documents(spark, rows))
    assert whole.columns == documents(spark, []).columns and whole.filter("text IS NULL").count() == 0


def slow_fingerprint(text):
    import xxhash

    w = words_of(re.sub("[A-Z]", lambda m: m[0].lower(), text or ""))
    if not w:
        return 0
    h = [xxhash.xxh64_intdigest(" ".join(w[i : i + 4]).encode(), 42) for i in range(max(1, len(w) - 3))]
    return sum(1 << b for b in range(64) if 2 * sum(x >> b & 1 for x in h) > len(h))


def classes(items, near):
    parent = list(range(len(items)))

    def root(x):
        while parent[x] != x:
            x = parent[x]
        return x

    for i in range(len(items)):
        for j in range(i):
            if near(items[i], items[j]) and root(i) != root(j):
                parent[max(root(i), root(j))] = min(root(i), root(j))
    return [root(i) for i in range(len(items))]


def test_simhash(spark, rows):
    got = simhash_bk.cluster(documents(spark, rows)).collect()
    fps = sorted((d, slow_fingerprint(t)) for d, t, _ in rows)
    groups = classes([f for _, f in fps], lambda a, b: (a ^ b).bit_count() <= 4)
    want = Counter((d, f"{f:016x}", fps[g][0]) for (d, f), g in zip(fps, groups, strict=True))
    assert Counter((r.doc_id, r.fingerprint, r.component_id) for r in got) == want
    assert simhash_bk.cluster(documents(spark, [])).count() == 0


@pytest.mark.parametrize("shard", [4096, 40])
def test_large_shards_lose_no_link(spark, shard):
    r = random.Random(2)
    base = r.getrandbits(64)
    values = {base ^ sum(1 << b for b in r.sample(range(64), r.choice([0, 1, 2, 3, 5, 9]))) for _ in range(300)} | {r.getrandbits(64) for _ in range(300)}
    values = sorted(values)
    signed = [v - (1 << 64) if v >> 63 else v for v in values]
    links = simhash_bk.near_links(spark.createDataFrame([(v,) for v in signed], "fp long"), 4, shard).collect()
    assert all((x.a ^ x.b).bit_count() <= 4 or ((x.a ^ x.b) & (2**64 - 1)).bit_count() <= 4 for x in links)
    have = {(x.a, x.b) for x in links}
    want = classes(signed, lambda a, b: ((a ^ b) & (2**64 - 1)).bit_count() <= 4)
    assert len(set(classes(signed, lambda a, b: (a, b) in have or (b, a) in have))) == len(set(want))


def test_wide_groups_find_near_copies(spark):
    r = random.Random(3)
    text = lambda n: [f"w{r.randint(0, 9999)}" for _ in range(n)]
    out, pairs = [], []
    for i in range(40):
        w = text(300)
        near = list(w)
        near[r.randint(0, 299)] = "changed"
        near[r.randint(0, 299)] = "other"
        out += [(2 * i, " ".join(w), "a"), (2 * i + 1, " ".join(near), "a")]
        pairs.append((2 * i, 2 * i + 1))
    out += [(200, None, "a"), (201, "", "a"), (202, "one two", "a"), (203, "one two", "a"), (203, "one two", "a")]
    got = {x.doc_id: x.component_id for x in simhash_bk.near_groups(documents(spark, out)).collect()}
    assert all(got[a] == got[b] == a for a, b in pairs)
    assert len(set(got.values())) == 42
    kept = simhash_bk.one_of_each(documents(spark, out))
    assert sorted(x.doc_id for x in kept.collect()) == [*range(0, 80, 2), 200, 202]


def shingles(text):
    w = words_of((text or "").lower())
    return {" ".join(w[i : i + 5]) for i in range(max(1, len(w) - 4))}


@pytest.mark.parametrize("shard", [4096, 7])
def test_near_groups_equal_brute_force(spark, shard):
    r = random.Random(8)
    text = lambda n: [f"w{r.randint(0, 9999)}" for _ in range(n)]
    common = text(12)
    out: list = []
    for i in range(150):
        w = text(r.choice([6, 7, 8, 12, 20, 60, 120, 300]))
        near = list(w)
        for _ in range(r.randint(1, max(1, len(w) // 12))):
            near[r.randrange(len(w))] = f"new{i}"
        if r.random() < 0.3:
            near += text(len(w) // 8)
        out += [w, near, *([common + text(r.choice([2, 4, 30]))] if i % 3 == 0 else [])]
    hub = text(100)
    for k in range(25):  # all near the hub, not near each other
        out.append([*hub[: 4 * k], "cut", *hub[4 * k + 1 :]] if k % 2 else [*hub, *[f"end{k}"] * 3, *text(14)])
    out = [(i, " ".join(w), "a") for i, w in enumerate([*out, hub])]
    out += [(5000, None, "a"), (5001, "", "a"), (5002, "one two", "a"), (5003, "One  two", "a"), (5004, "one two three", "a")]
    sets = [shingles(t) for _, t, _ in out]
    like = lambda a, b: len(a & b) / len(a | b)
    bands = Counter(min(9, int(10 * like(sets[i], sets[i + 1]))) for i in range(len(sets) - 1))
    assert all(bands[k] for k in (5, 6, 7, 8, 9))
    want = classes(sets, lambda a, b: 5 * len(a & b) >= 4 * len(a | b))
    got = {x.doc_id: x.component_id for x in simhash_bk.near_groups(documents(spark, out), shard=shard).collect()}
    assert got == {d: out[g][0] for (d, _, _), g in zip(out, want, strict=True)}


def test_near_groups_without_ids(spark):
    base = " ".join(f"w{i}" for i in range(100))
    out = [(None, base, "a"), (4, base, "a"), (3, base + " end", "a"), (None, "lone text of no id", "a"), (None, "lone text of no id", "a"), (9, "another one", "b"), (9, "and a third", "b")]
    got = Counter((x.doc_id, x.component_id) for x in simhash_bk.near_groups(documents(spark, out)).collect())
    assert got == Counter([(None, 3), (4, 3), (3, 3), (None, None), (None, None), (9, 9), (9, 9)])
    kept = Counter((x.doc_id, x.text) for x in simhash_bk.one_of_each(documents(spark, out)).collect())
    assert kept == Counter([(3, base + " end"), (None, "lone text of no id"), (9, "another one"), (9, "and a third")])
    assert simhash_bk.near_groups(documents(spark, [])).count() == 0


def test_phrase_fingerprints(spark, rows):
    own = [x for x in rows if not (x[0] == 107 and x[1] == "same id")][:-1]
    got = {r.doc_id: r for r in phrase_fingerprint.compare_edited(documents(spark, own), ranges=7).collect()}
    down = sorted(((d, t or "") for d, t, _ in own), reverse=True)
    for (d, t), (_, after) in zip(down, down[1:] + down[:1], strict=True):
        n = len(t) // 3
        edited = t[: len(t) - n] + after[:n]
        assert (got[d].n_chars, got[d].edited_sha256) == (len(t), hashlib.sha256(edited.encode()).hexdigest())
        a, b = (phrase_fingerprint.fingerprints([x.encode()]) for x in (t, edited))
        assert got[d].fingerprint == a.tobytes().hex() and got[d].edited_fingerprint == b.tobytes().hex()
        if len(t) > 300 and len(set(t)) > 5:
            assert got[d].near_edited > 0.35
    assert got[103].fingerprint == got[104].fingerprint == got[3].fingerprint and got[104].near_next == 1.0
    assert phrase_fingerprint.compare_edited(documents(spark, [])).count() == 0
    assert phrase_fingerprint.compare_edited(documents(spark, rows)).count() == len(rows)
    odd = phrase_fingerprint.compare_edited(documents(spark, [(5, "five five", "a"), (None, "none", "a"), (7, "seven", "a")])).collect()
    sha = lambda x: hashlib.sha256(x.encode()).hexdigest()
    assert {(x.doc_id, x.edited_sha256) for x in odd} == {(7, sha("sevef")), (5, sha("five fnon")), (None, sha("nons"))}


def test_phrases_are_local():
    r = random.Random(4)
    middle = bytes(r.choices(range(97, 123), k=3000))
    one = set(phrase_fingerprint.phrases([b"some prefix" + middle])[3][0].tolist())
    two = set(phrase_fingerprint.phrases([b"quite another, longer one" + middle + b"tail"])[3][0].tolist())
    assert len(one & two) > 0.95 * len(one)


def test_licenses(spark):
    texts = ["Cc-By cc by, CC BY!", "x\nLicensed under the Apache License, Version 2.0.\ny", "This is the GNU General  Public\nLicense; all rights RESERVED", None, "", "nothing here", "licensed by the under version of license apache 2 0 words"]
    got = {r.doc_id: r for r in license_join.scan(documents(spark, [(i, t, "a") for i, t in enumerate(texts)])).collect()}
    assert (got[0].n_words, got[0].n_base, got[0].first_word, got[0].last_word, got[0].base_labels) == (6, 3, 0, 4, "cc-by")
    assert got[1].labels == "apache-2.0" and got[1].n_base == 0 and got[1].score >= 0.8
    assert got[2].base_labels == "gpl,reserved" and got[2].n_base == 2
    assert all(got[i].score == 0 and got[i].labels == "" and got[i].first_word is None for i in (3, 4, 5))


def test_wrapped_licenses(spark):
    wrap = lambda text, n, sign="": "\n".join(sign + " ".join(text.split()[i : i + n]) for i in range(0, len(text.split()), n))
    wanted = {k: license_join.TEMPLATES[k][0].replace("*", "") for k in ("bsd", "lgpl", "agpl", "mpl-2.0")}
    texts = [(k, f"Some file\n\n{wrap(t, n, sign)}\n\ncode here") for k, t in wanted.items() for n in (3, 5, 7) for sign in ("", " * ", "# ")]
    apart = "redistribution and use in source " + "filler words here " * 9 + "binary forms with or without modification are permitted"
    got = {r.doc_id: r for r in license_join.scan(documents(spark, [*((i, t, "a") for i, (_, t) in enumerate(texts)), (900, apart.replace(" filler", "\nfiller"), "a")])).collect()}
    assert all(k in got[i].labels.split(",") and got[i].score >= 0.8 and got[i].n_blocks for i, (k, _) in enumerate(texts))
    assert got[900].labels == "" and got[900].n_blocks == 0


def test_confusable_licenses(spark):
    cases = {
        "This work is licensed under CC BY 4.0": "cc-by",
        "Licensed under a Creative Commons Attribution License.": "cc-by",
        "Licensed under CC BY-NC 4.0.": "cc-by,cc-by-nc",  # the base phrase stands in it too
        "Licensed under a Creative Commons Attribution-NonCommercial License": "cc-by-nc",
        "licensed under CC BY-NC-SA 4.0": "cc-by,cc-by-nc-sa",
        "This program is free software: you can redistribute it and/or modify it under the terms of the GNU General Public License": "gpl",
        "GNU Lesser General Public License as published by the Free Software Foundation": "gpl,lgpl",
        "GNU Affero General Public License as published by the Free Software Foundation": "agpl,gpl",
        "Released under the BSD license": "bsd",
        "released under the terms of the license": "",
        "the reserved seats have all the rights": "",
        "Released under the MIT License.": "mit",
        "Licensed under the Apache License, Version 2.0.": "apache-2.0",
        "This work is licensed under the GNU General Public License, version 3.": "gpl",
        "All rights reserved.": "reserved",
    }
    got = {r.doc_id: r.labels for r in license_join.scan(documents(spark, [(i, t, "a") for i, t in enumerate(cases)])).collect()}
    assert [got[i] for i in range(len(cases))] == list(cases.values())


def slow_hits(words, templates, threshold=0.8):
    """Every window of every template over a whole text, without filters or sliding counts."""
    runs = []
    for label, texts in templates.items():
        for text in texts:
            tokens, must = {w.rstrip("*") for w in text.split()}, {w[:-1] for w in text.split() if w.endswith("*")}
            span = -int(-len(text.split()) // threshold)
            own = []
            for end in range(len(words)):
                start = max(0, end - span + 1)
                inside = set(words[start : end + 1]) & tokens
                if len(inside) >= threshold * len(tokens) - 1e-9 and inside >= must:
                    if own and start <= own[-1][1]:
                        own[-1] = (own[-1][0], end)
                    else:
                        own.append((start, end))
            runs += [(label, frozenset(must), a, b) for a, b in own]
    return sorted({r[0] for r in runs if not any(r[1] < q[1] and q[2] <= r[3] and r[2] <= q[3] for q in runs)})


def test_whole_documents_equal_brute_force():
    r = random.Random(9)
    pool = "abcdefghij"
    templates = {f"t{i}": [" ".join(w + "*" * (r.random() < 0.3) for w in r.sample(pool, r.randint(2, 9)))] for i in range(10)}
    counts = {w.encode(): r.randint(0, 50) for w in pool}
    ready, index = license_join.compile_templates(templates, counts, 0.8)
    for _ in range(400):
        words = r.choices("abcdefghijklmnopqrstuvw", k=r.randint(0, 80))
        hits = license_join.most_specific(license_join.join_windows([w.encode() for w in words], ready, index), ready)
        assert sorted({ready[h[0]].label for h in hits}) == slow_hits(words, templates)


def test_media_round_trip(spark):
    texts = [None, "", "x" * 576, "é" * 3000, "x" * 577]
    got = {r.doc_id: r for r in iso_media.store(documents(spark, [(i, t, "a") for i, t in enumerate(texts)]), with_media=True).collect()}
    for i, t in enumerate(texts):
        body = (t or "").encode()
        padded = body + b"\xff" * (-len(body) % 576 if body else 576)
        info = iso_media.track(bytes(got[i].media))
        assert iso_media.payload(bytes(got[i].media), info) == padded
        assert (got[i].n_bytes, got[i].payload_bytes, got[i].payload_sha256, got[i].tail_crc32) == (len(body), len(padded), hashlib.sha256(padded).hexdigest(), zlib.crc32(padded[-32:]))
        assert got[i].media_sha256 == hashlib.sha256(bytes(got[i].media)).hexdigest() and got[i].media_bytes == len(got[i].media)
        assert [tuple(x) for x in got[i].keyframes] == info["keyframes"] == info["ranges"][::8] and got[i].codec == "raw" and got[i].seconds == len(padded) / 8000
    assert got[0].media_sha256 == got[1].media_sha256


def test_foreign_media(spark):
    good = iso_media.wrap(b"ab" * 288 * 5)
    empty = iso_media.box(b"trak", iso_media.box(b"mdia"))
    at = good.index(b"moov") - 4
    grown = int.from_bytes(good[at : at + 4], "big") + len(empty)
    first = good[:at] + grown.to_bytes(4, "big") + good[at + 4 : at + 8] + empty + good[at + 8 :]
    lost = good.replace(b"stsz", b"free")
    files = [good, first, lost, b"", None, b"\x89PNG not media", good[: len(good) // 2], b"\0\0\0\x08moov" * 3]
    rows = iso_media.describe(spark.createDataFrame(list(enumerate(files)), "id long, media binary")).collect()
    assert {r.id for r in rows} <= {0, 1, 6} and rows[0].samples == 5 and rows[0].codec == "raw " and len(rows[0].keyframes) == 1
    assert iso_media.track(b"") is None



def removed(rows):
    bodies = [(d, (t or "").encode()) for d, t, _ in rows]
    seen = Counter(b[i : i + 200] for _, b in bodies for i in range(len(b) - 199))
    out = []
    for d, b in bodies:
        gone = bytearray(len(b))
        for i in range(len(b) - 199):
            if seen[b[i : i + 200]] > 1:
                gone[i : i + 200] = b"\1" * 200
        rest = bytes(x for x, g in zip(b, gone, strict=True) if not g)
        out.append((d, len(b), len(b) - len(rest), len(re.findall(b"\1+", bytes(gone))), hashlib.sha256(rest).hexdigest()))
    return sorted(out)


@pytest.mark.parametrize("shard", [100_000, 2])
def test_repeated_spans(spark, rows, shard, monkeypatch):
    monkeypatch.setattr(suffix_dedup, "SHARD", shard)
    assert sorted(map(tuple, suffix_dedup.strip(documents(spark, rows)).collect())) == removed(rows)
    assert suffix_dedup.strip(documents(spark, [])).count() == 0


def test_spans_without_a_repeated_window():
    none = np.zeros(0, np.int64)
    assert [len(c) for c in suffix_dedup.intervals(none, none)] == [0, 0, 0]
    key, start = np.array([7, 5, 5, 5, 7]), np.array([3, 9, 1, 2, 4])
    assert [c.tolist() for c in suffix_dedup.intervals(key, start)] == [[5, 5, 7], [1, 9, 3], [2, 9, 4]]
    spans = [(1, 10, b"a" * 210), (1, 11, b"b" * 210), (2, 12, b"c" * 210)]
    batch = pa.RecordBatch.from_arrays([pa.array([h for h, *_ in spans]), pa.array([k for _, k, _ in spans]), pa.array([5] * 3), pa.array([x for *_, x in spans])], names=["h", "key", "place", "span"])
    assert [len(b) for b in suffix_dedup.sort_shards(iter([batch]))] == [0]


def test_encoder_equals_the_tokenizer():
    import public_tokenizers
    from tokenizers import Tokenizer

    whole = Tokenizer.from_file(public_tokenizers.path("byte_bpe_50k.json"))
    encode = token_packing.Encoder()
    for t in ["", " ", "a  b", " a", "a ", "\n", "a\n\nb", "it's don't\nWe'll", "x\ty\r\nz", "a <|endoftext|> b", "日本 語é", "1 2  3!!", "a\u00a0b c\u2003d", "The thing.\nAnd of***"]:
        assert np.frombuffer(encode(t), "<u4").tolist() == whole.encode(t, add_special_tokens=False).ids, t


def test_packing(spark, rows):
    import public_tokenizers
    from tokenizers import Tokenizer

    whole = Tokenizer.from_file(public_tokenizers.path("byte_bpe_50k.json"))
    got = token_packing.pack(documents(spark, rows)).collect()
    pieces, sequences = Counter(), defaultdict(list)
    for r in got:
        pieces[r.doc_id, r.piece, r.start, r.length, r.ids_crc32] += 1
        sequences[r.sequence_id].append((r.offset, r.length))
    want: Counter = Counter()
    for d, t, _ in rows:
        ids = [*whole.encode(t or "", add_special_tokens=False).ids, 0]
        at, k = 0, 0
        while at < len(ids):
            size = len(ids) % 2048 or 2048 if k == 0 else 2048
            want[d, k, at, size, zlib.crc32(np.array(ids[at : at + size], "<u4").tobytes())] += 1
            at, k = at + size, k + 1
    assert pieces == want
    for parts in sequences.values():
        at = 0
        for offset, length in sorted(parts):
            assert offset == at
            at += length
        assert at <= 2048
    assert len(sequences) <= 1.03 * -(-sum(r.length for r in got) // 2048) + 1
    assert token_packing.pack(documents(spark, [])).count() == 0


def test_plan_uses_every_piece_once():
    r = random.Random(7)
    for counts in ({}, {2048: 4}, {1: 9}, Counter(r.randint(1, 2048) for _ in range(3000)), {1500: 10**9, 500: 10**9, 47: 10**8}):
        plan = token_packing.Plan(dict(counts))
        seen: Counter = Counter()
        for n, gap, lengths in plan.runs:
            assert sum(lengths) + gap == 2048 and gap >= 0 < n
            for x in lengths:
                seen[x] += n
        assert seen == Counter(counts)


def test_url_rules(spark):
    urls = [None, "no scheme", "http://A.Example.COM/en/7x?q", "https://example.com/en/6", "http://b.net/de/8", "http://x.example.net/de/81#f", "http://myexample.net/de/8", "ftp://org", "http://org/es/", "x://a://b/en/"]
    pages = spark.createDataFrame([(i, u, "r", "h") for i, u in enumerate(urls)], "page_id long, url string, rule string, host string")
    got = {r.page_id: (r.host, r.path, r.rule, r.verdict) for r in url_rules.judge(pages).collect()}
    assert got[0] == got[1] == ("", "", None, "allow")
    assert got[2] == ("a.example.com", "/en/7x", "example.com/en/7", "allow") and got[3][2:] == ("com/en/", "block")
    assert got[4][2:] == ("net/de/", "allow") and got[5][2:] == ("example.net/de/8", "block") and got[6][2:] == ("net/de/", "allow")
    assert got[7] == ("org", "", None, "allow") and got[8][2] == "org/es/"
    rules = spark.createDataFrame([*url_rules.RULES, ("block", "", "/x"), ("block", None, "/x")], "verdict string, host string, path string")
    assert {r.page_id: (r.host, r.path, r.rule, r.verdict) for r in url_rules.judge(pages.select("page_id", "url"), rules, ranges=3).collect()} == got
    again = spark.createDataFrame([(1, "http://a.com/en/"), (1, "http://b.net/fr/"), (None, "http://b.net/de/")], "page_id long, url string")
    assert {(r.page_id, r.host, r.rule) for r in url_rules.judge(again).collect()} == {(1, "a.com", "com/en/"), (1, "b.net", None), (None, "b.net", "net/de/")}
    assert url_rules.judge(pages.limit(0)).count() == 0


def test_url_rules_of_the_contract(spark):
    words = {"com/en/": "block", "example.com/en/7": "allow", "net/de/": "allow", "example.net/de/8": "block", "org/es/": "block"}
    pages = spark.createDataFrame([(i, f"http://{rule}") for i, rule in enumerate(words)], "page_id long, url string")
    assert {r.rule: r.verdict for r in url_rules.judge(pages).collect()} == words
    connection = duckdb.connect()
    connection.sql("CREATE TABLE pages AS SELECT i AS page_id, 'http://' || rule AS url FROM (SELECT unnest(range(len($1))) AS i, unnest($1) AS rule)", params=[list(words)])
    assert dict(connection.sql(queries.ORACLE["op9_url_rules"]).select("rule", "verdict").fetchall()) == words


@pytest.mark.parametrize("ranges", [1, 5, 40])
def test_url_merge_equals_brute_force(spark, ranges):
    r = random.Random(ranges)
    host = lambda: ".".join(r.choices(["a", "b", "a-b", "com", "net", "é"], k=r.randint(1, 4)))
    path = lambda: "/" + "".join(r.choices("ab/", k=r.randint(0, 4)))
    rules = list({(h, p): (r.choice(["allow", "block"]), h, p) for h, p in ((host(), path()) for _ in range(60))}.values())
    urls = ["http://a.com/ab"] * 200 + [f"http://{host()}{path()}" for _ in range(300)]
    pages = spark.createDataFrame(list(enumerate(urls)), "page_id long, url string")
    got = {x.page_id: (x.rule, x.verdict) for x in url_rules.judge(pages, rules, ranges=ranges).collect()}
    for i, u in enumerate(urls):
        h, p = u[7:].split("/", 1)[0], "/" + u[7:].split("/", 1)[1]
        fit = [(len(a + b), a + b, v) for v, a, b in rules if (h == a or h.endswith("." + a)) and p.startswith(b)]
        best = max(fit, default=None)
        assert (got[i][0] is None) == (best is None)
        if best:
            assert len(got[i][0]) == best[0] and got[i] in {(t, v) for n, t, v in fit if n == best[0]}


def test_encoders_go_with_their_task():
    import gc
    import weakref

    gc.collect()
    gc.disable()
    try:
        encode = token_packing.Encoder()
        assert encode("one word\ntwo words")
        held = weakref.ref(encode.plain.__self__)
        del encode
        assert held() is None
    finally:
        gc.enable()


def test_quality(spark):
    docs = spark.read.parquet("/root/testdata/sf0.001/documents.parquet")
    labels = spark.read.parquet("/root/testdata/sf0.01/labels.parquet")
    all_docs = spark.read.parquet("/root/testdata/sf0.01/documents.parquet")
    half = labels.filter("doc_id % 2 = 0")
    got = {r.doc_id: r.keep for r in quality_bayes.classify(all_docs, half).collect()}
    held = [(r.doc_id, r.quality) for r in labels.filter("doc_id % 2 = 1").collect()]
    assert sum(got[d] == bool(y) for d, y in held) / len(held) > 0.95
    none = quality_bayes.classify(docs, labels.limit(0))
    assert none.count() == docs.count() and none.filter("NOT keep").count() == 0
    odd = documents(spark, [(1, None, None), (2, "", "a"), (2, "", "a"), (3, "Some words are here, and more.", "b")])
    assert quality_bayes.classify(odd, labels.limit(0)).count() == 4
    assert quality_bayes.keep_good(odd, labels.limit(0)).columns == odd.columns
    assert quality_bayes.classify(odd.limit(0), labels).count() == 0
