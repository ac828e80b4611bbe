"""Near copies, leaks, pages and the pipeline: brute force and edge cases."""

import random
import re

import numpy as np
import pytest
import xxhash

from spanwalk.llm import bpe, components, decontamination, embedding_dedup, html_extract, html_tree, langid, line_dedup, simhash


def least_reachable(nodes, near):
    comp = {n: n for n in nodes}
    again = True
    while again:
        again = False
        for a, b in near:
            low = min(comp[a], comp[b])
            if comp[a] != low or comp[b] != low:
                comp[a] = comp[b] = low
                again = True
    return comp


def test_components(spark):
    r = random.Random(1)
    links = [(r.randrange(200), r.randrange(200)) for _ in range(120)] + [(300 + k, 301 + k) for k in range(60)] + [(500, 500 + k) for k in range(1, 80)] + [(3, 3), (4, 5), (4, 5)]
    got = {x.node: x.component for x in components.connected_components(spark.createDataFrame(links, "a long, b long")).collect()}
    want = least_reachable({v for p in links if p[0] != p[1] for v in p}, links)
    assert got == want
    assert components.connected_components(spark.createDataFrame([], "a long, b long")).collect() == []


def plain_fingerprint(text, width=3):
    low = "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in text or "")
    w = re.findall(r"[^\x20\x09-\x0D]+", low)
    s = [" ".join(w[i : i + width]) for i in range(max(1, len(w) - width + 1))] if w else []
    ones = [0] * 64
    for x in s:
        h = xxhash.xxh64_intdigest(x.encode(), 42)
        for b in range(64):
            ones[b] += h >> b & 1
    return sum((ones[b] * 2 > len(s)) << b for b in range(64))


def test_fingerprints_and_spark_hash(spark):
    texts = [None, "", " \n", "one", "one TWO", "a b c", "A b C", "Éa b c d", "x " * 500, "tab\tand\x0bvt", "nbsp\xa0stays"]
    assert [simhash.fingerprint(t) for t in texts] == [plain_fingerprint(t) for t in texts]
    assert [simhash.fingerprint(t, 5) for t in texts] == [plain_fingerprint(t, 5) for t in texts]
    h = spark.sql("SELECT xxhash64('a b c') AS h").head().h
    assert h % 2**64 == xxhash.xxh64_intdigest(b"a b c", 42)


@pytest.mark.parametrize("most", [4000, 9])
def test_near_links_lose_nothing(spark, most):
    """Fingerprints around a few centres: components equal brute force, and buckets give forests only."""
    r = random.Random(2)
    bits = set()
    for _ in range(6):
        centre = r.getrandbits(64)
        for _ in range(60):
            x = centre
            for b in r.sample(range(64), r.randint(0, 5)):
                x ^= 1 << b
            bits.add(x)
    bits = sorted(bits)
    nodes = spark.createDataFrame([(b - (1 << 64) if b >> 63 else b, k) for k, b in enumerate(bits)], "b0 long, node long")
    links = simhash.near_links(nodes, most=most)
    near = [(i, j) for i in range(len(bits)) for j in range(i) if (bits[i] ^ bits[j]).bit_count() <= 3]
    got = {x.node: x.component for x in components.connected_components(links).collect()}
    want = least_reachable(range(len(bits)), near)
    assert {k: got.get(k, k) for k in want} == want
    assert all((bits[x.a] ^ bits[x.b]).bit_count() <= 3 for x in links.collect())


def test_simhash_groups(spark):
    r = random.Random(3)
    words = [f"w{k}" for k in range(400)]
    base = [" ".join(r.choice(words) for _ in range(r.randint(1, 300))) for _ in range(40)]
    texts = base + base[:10] + [b + " end" for b in base[:20]] + [None, "", "  "]
    rows = [(k, t, 0, "x") for k, t in enumerate(texts)] + [(3, base[3], 0, "x"), (None, base[0], 0, "x")]
    docs = spark.createDataFrame(rows, "doc_id long, text string, bits long, node string")
    got = simhash.digest(simhash.group_near_copies(docs)).collect()
    assert len(got) == len(rows)
    prints = {k: plain_fingerprint(t) for k, t, *_ in rows if k is not None}
    near = [(a, b) for a in prints for b in prints if a < b and (prints[a] ^ prints[b]).bit_count() <= 3]
    want = least_reachable(prints, near)
    for x in got:
        assert x.component_id == (None if x.doc_id is None else want[x.doc_id])
        assert x.fingerprint == f"{plain_fingerprint(base[0]) if x.doc_id is None else prints[x.doc_id]:016x}"
    kept = simhash.keep_one_of_each_group(docs, simhash.group_near_copies(docs))
    assert kept.columns == docs.columns
    assert {x.doc_id for x in kept.collect()} == {k for k, c in want.items() if k == c} | {None}
    assert simhash.group_near_copies(docs.limit(0)).collect() == []


def shingles(text, width=5):
    w = (text or "").lower().split()
    return {" ".join(w[i : i + width]) for i in range(max(1, len(w) - width + 1))}


def test_similar_texts(spark):
    """Edited copies of similarity 0.9 and more are found, texts below 0.6 and others are left alone."""
    r = random.Random(33)
    words = [f"w{k}" for k in range(3000)]
    rows, near, far = [], [], []
    for k in range(40):
        base = [r.choice(words) for _ in range(r.randint(120, 400))]
        copy = base[:]
        for _ in range(max(1, len(base) // (150 if k % 2 else 15))):
            copy[r.randrange(len(copy))] = "edit"
        rows += [(2 * k, " ".join(base)), (2 * k + 1, " ".join(copy))]
        a, b = shingles(rows[-2][1]), shingles(rows[-1][1])
        alike = len(a & b) / len(a | b)
        near += [2 * k] if alike >= 0.9 else []
        far += [2 * k] if alike < 0.6 else []
    assert len(near) > 10 and len(far) > 10
    rows += [(200, None), (201, "few words"), (202, "Few  WORDS"), (203, "few word"), (204, "")]
    docs = spark.createDataFrame([(*x, 5) for x in rows] + [(0, "another text under the first id " * 3, 5)], "doc_id long, text string, b0 int")
    got = {(x.doc_id, x.sign): x.component_id for x in simhash.group_similar(docs).collect()}
    comp = {k: c for (k, _), c in got.items() if k}
    assert sum(comp[k + 1] == k for k in near) >= 0.9 * len(near)
    assert all(comp[k + 1] == k + 1 for k in far)
    assert comp[202] == 201 and comp[203] == 203 and comp[204] == 200
    kept = simhash.keep_one_of_each_group(docs)
    assert kept.columns == docs.columns and sum(x.doc_id == 0 for x in kept.collect()) == 2


def plain_distance(pattern, text):
    """Fewest edits between the pattern and any stretch of the text."""
    prev = [0] * (len(text) + 1)
    for i, c in enumerate(pattern, 1):
        cur = [i]
        for j, y in enumerate(text, 1):
            cur.append(min(prev[j] + 1, cur[-1] + 1, prev[j - 1] + (c != y)))
        prev = cur
    return min(prev)


def edited(r, s, n):
    s = list(s)
    for _ in range(n):
        p, o = r.randrange(len(s)), r.random()
        if o < 0.4:
            s[p] = r.choice("xyz")
        elif o < 0.7:
            del s[p]
        else:
            s.insert(p, r.choice("xyz"))
    return "".join(s)


def test_gram_hashes_tell_rows_apart():
    text = "abcabcabdabc\u00e9\U0001f600abcab"
    for q in (1, 2, 3, 5, 8, 11):
        h = decontamination.gram_hashes(decontamination._letters(text), q)
        rows = [text[k : k + q] for k in range(len(text) - q + 1)]
        assert [[a == b for b in rows] for a in rows] == (h[:, None] == h[None, :]).tolist()


def test_leaks_against_brute_force():
    r = random.Random(6)
    prose = lambda n: " ".join("".join(r.choice("aeionrstlhd") for _ in range(r.randint(1, 8))) for _ in range(n))
    items = [(k, prose(r.randint(6, 60))) for k in range(12)]
    index = decontamination.PassageIndex(items)
    passages = {k: [t[at : at + 100] for at in range(max(1, len(t) - 99))] for k, t in items}
    edits = {k: int(index.edits[index.names.index(k)]) for k, _ in items}
    texts = []
    for _ in range(30):
        k = r.randrange(len(items))
        texts.append(f"{prose(15)} {edited(r, r.choice(passages[k]), r.randint(0, 12))} {prose(15)}")
    hits = 0
    for doc, found in zip(texts, decontamination.leaks_in(texts, index)):
        folded = decontamination.fold(doc)
        near = {k: [plain_distance(p, folded) for p in own[:: decontamination.FINE]] for k, own in passages.items() if sum(folded.find(p[x : x + 8]) >= 0 for p in own[::8] for x in range(0, len(p) - 7, 4)) > 2}
        got = {x[0]: x for x in found}
        for k, d in near.items():
            if min(d) <= edits[k]:
                assert k in got
        for k, x in got.items():
            assert x[4] <= edits[k]
            hits += 1
            inside = folded[len(decontamination.fold(doc[: x[1]] + "|")) - 1 : ][: x[2] - x[1]]
            assert min(plain_distance(p, inside) for p in passages[k]) <= x[4]
    assert hits > 12


def test_leaks_do_not_depend_on_runs_portions_or_parts(monkeypatch):
    r = random.Random(26)
    prose = lambda n: " ".join("".join(r.choice("aeionrstlhd") for _ in range(r.randint(1, 8))) for _ in range(n))
    items = [(k, prose(200)) for k in range(4)] + [(9, "ab" * 200), (10, "short one")]
    texts = [prose(30) + items[k % 4][1][30 * k : 30 * k + 140] + prose(200) for k in range(12)] + ["ab" * 700, None, "", "x\nShort  ONE \ny", "not a short one"]
    want = [{x[0] for x in f} for f in decontamination.leaks_in(texts, decontamination.PassageIndex(items))]
    assert want == [{k % 4} for k in range(12)] + [{9}, set(), set(), {10}, set()]
    monkeypatch.setattr(decontamination, "RUN_CHARS", 300)
    monkeypatch.setattr(decontamination, "PORTION", 50)
    assert [{x[0] for x in f} for f in decontamination.leaks_in(texts, decontamination.PassageIndex(items, part=250))] == want


def test_repetitive_texts_take_bounded_memory():
    import tracemalloc

    index = decontamination.PassageIndex([(1, "ab" * 60)])
    tracemalloc.start()
    (found,) = decontamination.leaks_of("ab" * 100_000, index)
    peak = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    assert found[:3] == (1, 0, 200_000) and peak < 150e6


def test_every_passage_of_a_segment_is_a_leak():
    r = random.Random(16)
    prose = lambda n: " ".join("".join(r.choice("aeionrstlhd") for _ in range(r.randint(1, 8))) for _ in range(n))
    items = [(k, prose(70)) for k in range(5)]
    index = decontamination.PassageIndex(items)
    for k, item in items:
        for at in range(0, len(item) - decontamination.SEGMENT + 1, 23):
            passage = item[at : at + decontamination.SEGMENT]
            assert k in {x[0] for x in decontamination.leaks_of(f"{prose(10)} {passage} {prose(10)}", index)}, at


def test_leaks(spark):
    r = random.Random(7)
    prose = lambda n: " ".join("".join(r.choice("aeionrstlhd") for _ in range(r.randint(1, 8))) for _ in range(n))
    items = [(k, prose(50)) for k in range(5)] + [(8, None), (9, ""), (10, "Tiny  one"), (None, prose(50))]
    texts = [None, "", prose(300), f"{prose(9)}\n{items[0][1].upper()}  {prose(9)}", items[1][1].replace(" ", "\n\t"), items[2][1][:180] + prose(40), items[3][1][:50] + prose(60), (items[4][1] + " ") * 3, "İ" * 30 + items[0][1], "a\n tiny ONE\nb", "no tiny one"]
    docs = spark.createDataFrame([(k, t, 1, 1) for k, t in enumerate(texts)] + [(3, texts[3], 1, 1)], "doc_id long, text string, item_id long, start long")
    bench = spark.createDataFrame(items, "item_id long, text string")
    got = decontamination.find_leaks(docs, bench).collect()
    assert sorted((x.doc_id, x.item_id) for x in got) == [(3, 0), (3, 0), (4, 1), (5, 2), (7, 4), (8, 0), (9, 10)]
    for x in got:
        inside = decontamination.fold(texts[x.doc_id][x.start : x.end])
        assert x.edits == 0 and inside in decontamination.fold(texts[x.doc_id])
        if x.doc_id in (3, 4, 8, 9):
            assert inside == decontamination.fold(dict(items)[x.item_id])
    blocks = decontamination.find_leaks(docs, bench, block_chars=300).collect()
    assert sorted(map(tuple, blocks)) == sorted(map(tuple, got))
    assert sorted(x.doc_id for x in decontamination.clean_documents(docs, bench, block_chars=300).collect()) == [0, 1, 2, 6, 10]
    long_item = spark.createDataFrame([(1, prose(15_000))], "item_id long, text string")
    piece = long_item.head().text[50_000:50_150]
    one = spark.createDataFrame([(7, f"{prose(20)} {piece}")], "doc_id long, text string")
    assert [(x.doc_id, x.item_id, x.edits) for x in decontamination.find_leaks(one, long_item).collect()] == [(7, 1, 0)]
    kept = decontamination.clean_documents(docs, bench)
    assert kept.columns == docs.columns and sorted(x.doc_id for x in kept.collect()) == [0, 1, 2, 6, 10]
    assert decontamination.find_leaks(docs, bench.limit(0)).collect() == [] == decontamination.find_leaks(docs.limit(0), bench).collect()


@pytest.mark.parametrize("block", [2000, 16])
def test_embeddings(spark, block):
    r = np.random.default_rng(4)
    rows = []
    for label in (0, 1, None):
        for c in r.standard_normal((25, 16)):
            for _ in range(int(r.integers(1, 5))):
                rows.append((len(rows), (c + r.standard_normal(16) * r.choice([0.0, 0.02, 0.15])).astype(np.float32).tolist(), label))
    hot = r.standard_normal(16)
    rows += [(len(rows) + k, (hot + r.standard_normal(16) * 0.05).astype(np.float32).tolist(), 2) for k in range(70)]
    n = len(rows)
    odd = [None, [0.0] * 16, [float("nan")] * 16, [1.0] * 15 + [None], [float("inf")] * 16, [1.0, 2.0], [], [2.0 * x for x in rows[0][1]]]
    rows += [(n + k, v, 0) for k, v in enumerate(odd)] + [rows[5], (None, rows[0][1], 0)]
    vectors = spark.createDataFrame([(*x, 7) for x in rows], "vec_id long, embedding array<float>, label int, n_links int")
    got = embedding_dedup.link_embeddings(vectors, block=block).collect()
    assert len(got) == len(rows)
    good = {k: (label, np.array(v, dtype=np.float64)) for k, v, label in rows if k is not None and label is not None and v is not None and len(v) == 16 and None not in v and np.isfinite(v).all() and any(v)}
    cos = lambda a, b: a @ b / np.linalg.norm(a) / np.linalg.norm(b)
    near = [(a, b) for a in good for b in good if a < b and good[a][0] == good[b][0] and cos(good[a][1], good[b][1]) >= 0.93]
    comp = least_reachable({x[0] for x in rows if x[0] is not None}, near)
    links = {k: sum(k in p for p in near) for k in comp}
    found = sum(x.n_links for x in got if x.vec_id is not None)
    assert all(x.n_links <= links[x.vec_id] for x in got if x.vec_id is not None)
    assert found >= 0.9 * sum(links.values())
    same = sum(x.component_id == comp[x.vec_id] and x.kept == (x.vec_id == comp[x.vec_id]) for x in got if x.vec_id is not None)
    assert same >= 0.97 * len(comp)
    assert embedding_dedup.link_embeddings(vectors.limit(0)).collect() == []


def test_embeddings_of_any_length_scale_and_label(spark):
    long = "label " * 40
    rows = [(1, [1.0, 0.0], "x"), (2, [1.0, 0.01], "x"), (3, [1.0, 0.0, 0.0], "x"), (4, [1.0, 0.02, 0.0], "x"), (5, [3e-200, 4e-200, 0.0], long), (6, [3e200, 4.01e200, 0.0], long), (7, [3.0, 4.0, 0.0], "x")]
    rows += [(8, [1.0, 0.0], "9999999999999"), (9, [1.0, 0.001], "9999999999999"), (10, [1.0, 0.0], "y"), (10, [0.0, 1.0], "y"), (11, [1.0, 0.0], "y"), (12, [0.0, 1.0], "y")]
    got = embedding_dedup.link_embeddings(spark.createDataFrame(rows, "vec_id long, embedding array<double>, label string")).collect()
    assert len(got) == len(rows)
    comp = {x.vec_id: (x.n_links, x.component_id, x.kept) for x in got}
    assert comp[1] == (1, 1, True) and comp[2] == (1, 1, False) and comp[4] == (1, 3, False) and comp[6] == (1, 5, False) and comp[7] == (0, 7, True) and comp[9] == (1, 8, False)
    assert len({(x.n_links, x.component_id, x.kept) for x in got if x.vec_id == 10}) == 1
    assert sorted([comp[11][1], comp[12][1]]) in ([10, 12], [10, 11]) and comp[10] == (1, 10, True)


def test_table_plan():
    for n in (10, 10_000, 10**7, 10**10):
        bits, tables = embedding_dedup.plan_tables(n)
        agree = (1 - np.arccos(0.93) / np.pi) ** bits
        assert 1 - (1 - agree) ** tables >= 0.995


def test_tree():
    page = html_tree.Page("<p>a<p>b<div>c<script>var x='</p>'</script>d</div><!-- x --><ul><li>1<li>2</ul><br>e &amp;lt; f")
    assert page.blocks([True] * len(page.tag)) == ["a", "b", "cd", "1", "2", "e &lt; f"]
    assert html_tree.unescape("a &amp; b &lt;&#233;&amp;amp;") == "a & b <é&amp;"
    for broken in ("", "<", "<a", "<p", "text <b", "<div><div><div>", "</p></div>x", "<!--", "<p class='x>y</p>"):
        html_tree.Page(broken)


def blocks_of(source):
    page = html_tree.Page(source)
    return page.blocks([True] * len(page.tag))


def test_unclosed_elements_drop_nothing_else():
    for name in ("svg", "noscript", "object", "canvas", "template", "math", "select"):
        assert blocks_of(f"<p>a</p><{name}><x>hid</x></{name}><p>b</p>") == ["a", "b"]
        assert "rest" in blocks_of(f"<p>a</p><{name}><path d='M1'/><p>rest</p>")
    assert blocks_of("x<center>Foo</center>y") == ["x", "Foo", "y"]
    assert blocks_of("a < b <3 <p title='>'>c</p><p class='x>y</p>z") == ["a < b <3", "c", "y", "z"]
    assert blocks_of("&#" + "9" * 6000 + "; &#0000065;") == ["\ufffd A"]


@pytest.mark.parametrize("source", ['<b ' * 350_000, '<a href="x' * 100_000, '<a "' * 250_000 + ">", '<a " > " ' * 110_000, "<div>" * 200_000, "<td><table>" + "<div>" * 70_000 + "<td></td>" * 70_000, "<!--" * 250_000, "<" * 300_000, "&" * 1_000_000, "<svg>" * 200_000])
def test_hostile_pages_take_linear_time(source):
    import time

    def seconds(s):
        began = time.process_time()
        page = html_tree.Page(s)
        page.blocks([True] * len(page.tag))
        return time.process_time() - began

    assert seconds(source) < 8  # a quadratic parser needs minutes and more


def test_tokens_against_the_standard_parser():
    from html.parser import HTMLParser

    class Plain(HTMLParser):
        def __init__(self):
            super().__init__(convert_charrefs=False)
            self.seen = []

        def handle_starttag(self, tag, attrs):
            self.seen.append(tag)

        def handle_endtag(self, tag):
            self.seen.append("/" + tag)

    r = random.Random(31)
    for _ in range(200):
        source = "".join(r.choice(["<p>", "</p>", "<div class='a>b'>", '<a href="x">', "</a>", "text ", "<br>", "<!-- <p> -->", "1 < 2 ", "<h2 id=q>", "</h2>", "<!DOCTYPE html>", "<ul><li>x", "<script>if (a<b) '</p>'</script>"]) for _ in range(30))
        plain = Plain()
        plain.feed(source)
        assert [n for _, n, _ in html_tree.tokens(source) if n] == [x for x in plain.seen if x != "/script"]


@pytest.fixture(scope="module")
def trees():
    return html_extract.model()


def test_pages(trees):
    story = ["This is the first paragraph of the story, and it says something of note.", "Second paragraph. It has two sentences.", "Short one."]
    want = "\n".join(["Title here", *story])
    noise = ["<nav><ul><li><a href=/a>Home</a></li><li><a href=/b>News</a></li></ul></nav>", "<header><h1>Site name</h1><p>Our slogan is here.</p></header>", "<footer>&copy; 2024 Example. All rights reserved.</footer>", '<aside class="sidebar"><h3>Popular</h3><p>Read this other thing now.</p></aside>', '<div class="cookie-notice"><p>We use cookies to make this site better.</p></div>', '<div class="ad">Buy now, cheap things for sale.</div>', "<form><label>Email</label><input name=e><p>Sign up to our letter.</p><button>Go</button></form>", '<section class="comments"><h2>Comments</h2><div class="comment"><p>I liked this a lot, thank you for it.</p></div></section>']
    for block in noise:
        for before, inside, after in ((block, "", ""), ("", block, ""), ("", "", block)):
            source = f"<html><head><title>x</title></head><body>{before}<article><h1>Title here</h1>{''.join(f'<p>{s}</p>' for s in story)}{inside}</article>{after}</body></html>"
            assert html_extract.main_texts([source], trees) == [want], block


def test_hierarchy_never_contradicts(trees):
    r = random.Random(12)
    exact = 0
    for _ in range(60):
        source, mark = html_extract.training_page(r)
        page = html_tree.Page(source)
        rows, own, sub = html_extract.features(page)
        kept = html_extract.decode(page, trees.logit(rows(0, len(own))), own, sub)
        assert all(kept[page.parent[v]] for v in range(1, len(kept)) if kept[v])
        text = html_extract.main_texts([source], trees)[0]
        exact += text.count(mark) == source.count(mark) and all(mark in line for line in text.split("\n"))
    assert exact >= 45


def test_pages_frame(spark):
    rows = [(1, "u", None, "t"), (2, None, "", "t"), (None, "v", "<article><h1>A title</h1><p>Some words of a story that go on.</p></article>", "t"), (3, "w", "<article><p>Some words of a story that go on, " + "and on " * 3000 + "</article>", "t")]
    got = html_extract.digest(html_extract.extract_pages(spark.createDataFrame(rows, "page_id long, url string, html string, text string"))).collect()
    assert [(x.page_id, x.url, x.text == "", x.n_chars == len(x.text)) for x in got] == [(1, "u", True, True), (2, None, True, True), (None, "v", False, True), (3, "w", False, True)]


def test_pipeline(spark, tmp_path):
    """Every stage against its brute-force twin on a small corpus."""
    import corpus_pipeline

    r = random.Random(9)
    words = {"en": ["the", "thing", "other", "with", "that", "and", "of"], "de": ["der", "schule", "und", "nicht", "über", "ein"]}
    prose = lambda lang, n: " ".join(r.choice(words[lang]) + r.choice(["", "s", "er", "ing"]) for _ in range(n))
    rows = [(k, "\n".join(prose(lang, 25) for _ in range(4)), lang, "s", 0) for k in range(80) for lang in [("en", "de")[k % 2]]]
    item = prose("en", 40)
    rows += [(100, rows[0][1], "en", "s", 0), (101, None, "en", "s", 0), (102, "1234 5678", None, "s", 0), (103, prose("en", 20) + " " + item, "en", "s", 0), (104, rows[2][1].split("\n")[0] + "\n" + prose("en", 60), "en", "s", 0)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long")
    docs.coalesce(2).write.parquet(str(tmp_path / "documents.parquet"))
    spark.createDataFrame([(1, item)], "item_id long, text string").write.parquet(str(tmp_path / "benchmark.parquet"))
    assert [f.__name__ for _, f in corpus_pipeline.STAGES] and 4 <= len(corpus_pipeline.STAGES) <= 5
    now = {k: t for k, t, *_ in rows}
    now = {k: t for k, t in now.items() if langid.has_letter(t)}
    holders = {}
    for k, t in now.items():
        for line in t.split("\n"):
            holders.setdefault(line.strip().lower(), set()).add(k)
    now = {k: "\n".join(x for x in t.split("\n") if len(x.strip()) < 10 or min(holders[x.strip().lower()]) == k) for k, t in now.items()}
    key_bits, width = simhash.plan_wide(len(now))
    prints = {k: [int(x) for x in simhash.wide_fingerprint(t, 5, width)] for k, t in now.items()}
    apart = lambda a, b: sum((x ^ y).bit_count() for x, y in zip(prints[a], prints[b]))
    comp = least_reachable(prints, [(a, b) for a in prints for b in prints if a < b and apart(a, b) <= simhash.wide_distance(0.8, width)])
    now = {k: t for k, t in now.items() if comp[k] == k}
    index = decontamination.PassageIndex([(1, item)])
    now = {k: t for k, t in now.items() if not decontamination.leaks_of(t, index)}
    enc = bpe.encoder(bpe.default_vocabulary())
    got = {x.doc_id: x.n_tokens for x in corpus_pipeline.run(spark, str(tmp_path)).collect()}
    assert got == {k: len(enc.encode(t)) for k, t in now.items()}
    assert 103 not in got and 101 not in got and 102 not in got
    assert line_dedup.LEAST == 10
