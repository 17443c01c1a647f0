"""Each operator against a brute-force version on small tables with nulls, empty, long and repeated rows and clashing columns."""

import hashlib
import re
import zlib
from itertools import product

import numpy as np
import pytest
import xxhash
from hypothesis import given, settings
from hypothesis import strategies as st
from pyspark.sql import functions as F

from quadpost.llm import chat, decontamination, html, language, lines, neighbours, packing, queries, sharding, simhash, substrings, tokens
from tests.conftest import SMALL

DOCS = "doc_id bigint, text string, lang string, prefix string, doc bigint, depth int, rank int"
RNG = np.random.default_rng(0)
WORDS = ["alpha", "beta", "gamma", "delta", "Straße", "été", "x", "l'eau", "42"]


def prose(n):
    return " ".join(RNG.choice(WORDS, n)) + "."


BASE = prose(400)
TEXTS = [None, "", " \n\t ", "one", "One two", prose(5), BASE, BASE, BASE + " tail words here", "head " + BASE, prose(60), prose(3000), "same line of five words here\n" * 4 + prose(30), "same line of five words here\nother", "short\nlines\nonly", "short\nlines\nagain", "!!! 123 ---", "a b c\x0bd"]


@pytest.fixture(scope="module")
def docs(spark):
    rows = [(i, t, "en" if i % 2 else "de", "p", i, 1, 2) for i, t in enumerate(TEXTS)]
    rows += [rows[6], rows[11], (None, BASE, None, None, None, None, None), (None, None, None, None, None, None, None)]
    return spark.createDataFrame(rows, DOCS)


@pytest.fixture(scope="module")
def empty(spark):
    return spark.createDataFrame([], DOCS)


def pairs(docs):
    return [(r["doc_id"], r["text"]) for r in docs.collect()]


@pytest.mark.parametrize("name", sorted(queries.oracle_sql()))
def test_query_equals_oracle(name, same):
    same(name, queries.queries(), queries.oracle_sql())


# --- 1 -----------------------------------------------------------------------------------------------------------------


def test_messages_give_the_exact_marginals():
    nodes = [html.Node("div", (), p) for p in (-1, 0, 0, 1, 1, 2)]
    potentials = [0.3, -1.2, 0.7, 2.0, -0.4, 0.1]
    model = html.TreeModel({}, 0.0, [[1.9, 0.3], [0.2, 4.0]], [0.6, 0.4])
    weight = np.zeros((len(nodes), 2))
    for states in product((0, 1), repeat=len(nodes)):
        w = model.root[states[0]] * np.exp(sum(p * s for p, s in zip(potentials, states, strict=True)))
        for n, s in zip(nodes[1:], states[1:], strict=True):
            w *= model.edges[states[n.parent]][s]
        for i, s in enumerate(states):
            weight[i, s] += w
    assert model.marginals(nodes, potentials) == pytest.approx((weight[:, 1] / weight.sum(axis=1)).tolist())


def test_pair_expectations_are_exact():
    nodes = [html.Node(t, (), p) for t, p in (("#page", -1), ("body", 0), ("div", 1), ("p", 2), ("p", 2))]
    potentials = [0.2, -0.7, 1.1, 0.4, -1.5]
    model = html.TreeModel({}, 0.0, [[1.9, 0.3], [0.2, 4.0]], [0.6, 0.4], [[1.1, 0.8], [0.5, 1.3]])
    pair = np.zeros((len(nodes), 2, 2))
    for states in product((0, 1), repeat=len(nodes)):
        w = model.root[states[0]] * np.exp(sum(p * s for p, s in zip(potentials, states, strict=True)))
        for n, s in zip(nodes[1:], states[1:], strict=True):
            w *= (model.frame_edges if nodes[n.parent].tag in html.FRAME_TAGS else model.edges)[states[n.parent]][s]
        for i in range(1, len(nodes)):
            pair[i, states[nodes[i].parent], states[i]] += w
    got = model.expected(nodes, potentials)[1]
    for i in range(1, len(nodes)):
        assert np.array(got[i]) == pytest.approx(pair[i] / pair[i].sum())


@pytest.mark.parametrize("layout", html.LAYOUTS)
def test_held_out_pages(layout):
    right = total = 0
    for page, content in html.labelled_pages(60, seed=77, layout=layout):
        got = html.main_blocks(page, html.trained())
        right += len(set(got) & set(content)) * 2
        total += len(got) + len(content)
    assert right / total > 0.93


def test_an_unseen_layout():
    """Learned without bare and plain pages, asked for bare ones."""
    data = [(html.parse(page), content) for kind in ("named", "nested", "table") for page, content in html.labelled_pages(120, seed=9, layout=kind)]
    model = html.fit([(nodes, html.labels_of(nodes, blocks, content)) for (nodes, blocks), content in data])
    right = total = 0
    for page, content in html.labelled_pages(40, seed=78, layout="bare"):
        got = html.main_blocks(page, model)
        right += len(set(got) & set(content)) * 2
        total += len(got) + len(content)
    assert right / total > 0.85


def _paragraphs(n):
    return [" ".join(f"word{k} and some more text," for _ in range(15)) for k in range(n)]


@pytest.mark.parametrize("n", [1, 2, 3, 5])
@pytest.mark.parametrize("frame", ["<body>{}</body>", "<html><head><title>t</title></head><body>{}</body></html>", "<body><div>{}</div></body>", "{}", "<body><header><a href=x>Start</a></header>{}<footer>&copy; 2020 all rights</footer></body>"])
def test_bare_pages_keep_their_paragraphs(frame, n):
    texts = _paragraphs(n)
    assert html.main_blocks(frame.format("".join(f"<p>{t}</p>" for t in texts)), html.trained()) == texts
    head = "A short title"
    assert html.main_blocks(frame.format(f"<h1>{head}</h1>" + "".join(f"<p>{t}</p>" for t in texts)), html.trained()) == [head, *texts]


def test_text_that_stands_in_the_page_itself():
    a, b, c = _paragraphs(3)
    for page, want in ((a, [a]), (f"<body>{a}</body>", [a]), (f"<body>{a}<p>{b}</p>{c}</body>", [a, b, c]), (f"{a}<br>{b}", [f"{a} {b}"])):
        assert html.main_blocks(page, html.trained()) == want


@pytest.mark.parametrize("piece", ['<a "', '<a x="', "</script ", "<noscript>", '<div class="x{}">', "</div", "<a<b", "<title", '<p title="x', "=  ", "<!--", "</p>", "<li>"])
def test_broken_pages_are_read_in_linear_time(piece):
    from time import process_time

    page = "".join(piece.replace("{}", "a" * (i % 7)) for i in range(1_000_000 // len(piece))) + "<p>end"
    began = process_time()
    html.main_blocks(page, html.trained())
    assert process_time() - began < 20


def test_pages_of_the_table(spark):
    def article(page):
        inner = page.split("<article>", 1)[1].split("</article>")[0]
        parts = [" ".join(html._references.unescape(re.sub(r"<[^>]*>", "", b.replace("<br>", " "))).split()) for b in re.split(r"</?(?:p|h1)>", inner)]
        return "\n\n".join(p for p in parts if p)

    pages = spark.read.parquet(f"{SMALL}/pages.parquet")
    want = {r["page_id"]: article(r["html"]) for r in pages.collect()}
    assert {r["page_id"]: r["text"] for r in html.extract(pages).collect()} == want


def test_odd_pages(spark):
    long = " ".join(_paragraphs(1)) * 4000
    rows = [(1, "u", None, "x", 1), (2, "u", "", "x", 1), (3, None, "<article><p>cut of", "x", 1), (4, "u", "<p>a &lt; b<script>if(1){'<p>no</p>'}</script></p><!-- <p>no", "x", None), (1, "u", None, "x", 1), (5, "u", "no tags at all", None, 1), (None, "u", f"<body><p>{long}</p></body>", "x", 1)]
    table = spark.createDataFrame(rows, "page_id bigint, url string, html string, text string, n_chars int")
    got = html.extract(table).collect()
    assert len(got) == 7 and all(r["n_chars"] == len(r["text"]) for r in got) and html.extract(table).columns == ["page_id", "url", "text", "n_chars"]
    assert sorted(((r["page_id"], r["text"]) for r in got), key=str) == sorted([(1, ""), (2, ""), (3, "cut of"), (4, "a < b"), (1, ""), (5, "no tags at all"), (None, long.rstrip())], key=str)
    assert html.extract(table.limit(0)).count() == 0


def test_the_tree_of_a_page():
    tree = lambda page: [(t, (nodes := html.parse(page)[0])[nodes[i].parent if nodes[i].tag == html.TEXT_TAG else i].tag) for i, t in html.parse(page)[1]]
    assert tree("<div>x<p>y</div>z") == [("x", "div"), ("y", "p"), ("z", "#page")]
    assert tree("<p>a<p>b<ul><li>c<li>d</ul><td>e") == [("a", "p"), ("b", "p"), ("c", "li"), ("d", "li"), ("e", "td")]
    assert tree("x <y z=\"1>2\"> w</y> < 3 <b") == [("x w < 3", "#page")]
    assert tree("<p>a<i title=it's>b</i></p>c") == [("ab", "p"), ("c", "#page")]


@pytest.mark.parametrize("tag", ["svg", "math", "noscript", "template"])
def test_left_out_elements_end_with_their_parents(tag):
    words = lambda page: [t for _, t in html.parse(page)[1]]
    assert words(f"<div>a<{tag}><p>no</p>{'<b>' * 3}<script>'</div>'</script></div><p>b</p>") == ["a", "b"]
    assert words(f"<div>a<{tag}><div>no</div>no</{tag}>c</div><p>b</p>") == ["ac", "b"]
    assert words(f"<p>a<{tag}><{tag}>no</{tag}>no</{tag}>c</p>b") == ["ac", "b"]
    if tag in ("svg", "math"):
        assert words(f'<p>a<{tag} class="i"/>b</p><p>c</p><{tag}><g>no</g></{tag}><p>d</p>') == ["ab", "c", "d"]


# --- 2 -----------------------------------------------------------------------------------------------------------------


def brute_contamination(texts, items, size):
    split = lambda t: re.findall(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+", re.sub("[A-Z]", lambda m: m[0].lower(), t or ""))
    out = []
    for doc, text in texts:
        w, hit, ids = split(text), set(), set()
        for item, passage in items:
            b = split(passage)
            for i in range(max(1, len(b) - size + 1) if b and item is not None else 0):
                g = b[i : i + size]
                for j in range(len(w) - len(g) + 1):
                    if w[j : j + len(g)] == g:
                        hit |= set(range(j, j + len(g)))
                        ids.add(str(item))
        out.append((doc, len(w), len(hit), len(ids), hashlib.sha256(",".join(sorted(ids)).encode()).hexdigest(), bool(hit) and 20 * len(hit) >= len(w)))
    return sorted(out, key=str)


BENCHMARK = "item_id bigint, text string, doc_id string, term int, extra int"


@pytest.mark.parametrize("segment", [4096, 3, 1])
def test_contamination(spark, docs, segment):
    items = [(1, BASE[:150]), (20, "ONE"), (3, None), (None, "one"), (4, "!!"), (1, "one two"), (5, prose(20)), (6, "x"), (7, "word that nowhere stands"), (8, prose(500)), (9, "same line of five words here other"), (10, "")]
    got = decontamination.contamination(docs, spark.createDataFrame([(*r, "d", 1, None) for r in items], BENCHMARK), segment_docs=segment)
    assert got.columns == ["doc_id", "n_words", "n_hit", "n_items", "items_sha256", "contaminated"]
    assert sorted(map(tuple, got.collect()), key=str) == brute_contamination(pairs(docs), items, 13)


def test_contamination_of_empty_tables(spark, docs, empty):
    none = spark.createDataFrame([], BENCHMARK)
    assert decontamination.contamination(empty, none).count() == 0
    assert decontamination.contamination(empty, spark.createDataFrame([(1, "one", "d", 1, 1)], BENCHMARK)).count() == 0
    got = decontamination.contamination(docs, none).collect()
    assert len(got) == docs.count() and {r["contaminated"] for r in got} == {False} and {r["items_sha256"] for r in got} == {hashlib.sha256(b"").hexdigest()}


def test_the_index_has_every_posting(spark, docs):
    index = decontamination.build_index(docs)
    total = sum(len(decontamination.words(t)) for _, t in pairs(docs))
    assert index.where("term != 0").agg(F.sum("n"), F.sum(F.size("positions"))).first() == (total, total)
    assert sorted(map(tuple, decontamination.documents(index).select("doc_id", "n_words").collect()), key=str) == sorted(((d, len(decontamination.words(t))) for d, t in pairs(docs)), key=str)


def test_proximity(spark, docs):
    df = spark.createDataFrame([(1, "a b c d e"), (2, "a x x x e"), (3, "e a"), (None, "e"), (5, None)], "doc_id bigint, text string")
    index = decontamination.build_index(df)
    asked = spark.createDataFrame([(7, "A e", 1), (8, "b", 1), (None, "a", 1), (9, None, 1), (10, "a nowhere", 1)], "item_id bigint, text string, doc_id int")
    ask = lambda within: {(r["item"], r["doc_id"]) for r in decontamination.proximity_hits(index, asked, within).collect()}
    assert ask(1) == {("7", 3), ("8", 1)} and ask(4) == {("7", 1), ("7", 2), ("7", 3), ("8", 1)}


@pytest.mark.parametrize("within", [2, 6])
def test_proximity_equals_brute_force(spark, docs, within):
    terms = ["gamma", "42", "x"]
    few = docs.where("doc_id IS NOT NULL").dropDuplicates(["doc_id"]).coalesce(1)
    ws = {d: [w.decode() for w in decontamination.words(t)] for d, t in pairs(few)}
    rarest = min(terms, key=lambda t: sum(w.count(t) for w in ws.values()))
    want = {(d, p) for d, w in ws.items() for p, v in enumerate(w) if v == rarest and all(t in w[max(0, p - within) : p + within + 1] for t in terms)}
    got = decontamination.proximity_hits(decontamination.build_index(few), spark.createDataFrame([(1, " ".join(terms))], "item_id int, text string"), within)
    assert {(r["doc_id"], r["position"]) for r in got.collect()} == want and want


# --- 3 -----------------------------------------------------------------------------------------------------------------


def brute_lines(texts):
    order = sorted({(d is not None, d if d is not None else 0, t) for d, t in texts if t is not None}, key=lambda x: x[:2])
    single, double, cut = set(), set(), {}
    for key in order:
        part, gone = key[2].split("\n"), set()
        solid = [bool(p.strip()) for p in part]
        for i, p in enumerate(part):
            if not solid[i]:
                continue
            if p in single and len(p.split()) >= lines.MIN_WORDS:
                gone.add(i)
            if i + 1 < len(part) and solid[i + 1] and (p, part[i + 1]) in double:
                gone |= {i, i + 1}
            single.add(p)
            if i + 1 < len(part) and solid[i + 1]:
                double.add((p, part[i + 1]))
        cut[key] = (len(part), len(gone), "\n".join(p for i, p in enumerate(part) if i not in gone))
    return sorted(((d, *(cut[(d is not None, d if d is not None else 0, t)] if t is not None else (0, 0, None))) for d, t in texts), key=str)


def test_line_dedup(docs, empty):
    got = lines.dedup_lines(docs)
    assert set(docs.columns) <= set(got.columns)
    assert sorted(((r["doc_id"], r["n_lines"], r["n_removed"], r["text"]) for r in got.collect()), key=str) == brute_lines(pairs(docs))
    assert lines.dedup_lines(empty).count() == 0


def test_suffix_rounds_find_the_common_prefixes(spark):
    body = "\n".join(f"line {i} of the run" for i in range(9))
    df = spark.createDataFrame([(1, body + "\nend"), (2, "start\n" + body)], "doc_id bigint, text string")
    rounds = {size: found.count() for size, found in lines.suffix_rounds(lines.line_ids(df), 8)}
    assert rounds == {1: 18, 2: 16, 4: 12, 8: 4}


def test_doubling_goes_on_until_nothing_repeats(spark):
    body = "\n".join(f"line {i} of the run" for i in range(21))
    df = spark.createDataFrame([(1, body), (2, "start\n" + body), (3, "x")], "doc_id bigint, text string")
    assert [size for size, _ in lines.suffix_rounds(lines.line_ids(df))] == [1, 2, 4, 8, 16]
    assert lines.repeated_runs(lines.line_ids(df.where("doc_id = 3"))) is None


def test_repeated_runs_have_exact_lengths(spark):
    rng = np.random.default_rng(8)
    texts = [[f"l{x}" for x in rng.integers(0, 12, n)] for n in (30, 40, 25, 60)] + [["l1"] * 30]
    texts.append(texts[0][3:25] + texts[1][5:38])
    df = spark.createDataFrame([(i, "\n".join(t)) for i, t in enumerate(texts)], "doc_id bigint, text string")
    spots = [(d, p) for d, t in enumerate(texts) for p in range(len(t))]

    def common(a, b):
        (d, p), (e, q), n = a, b, 0
        while p + n < len(texts[d]) and q + n < len(texts[e]) and texts[d][p + n] == texts[e][q + n]:
            n += 1
        return n

    longest = {s: max((common(s, o) for o in spots if o < s), default=0) for s in spots}
    got = lines.repeated_runs(lines.line_ids(df)).collect()
    covered = {}
    for r in got:
        here, source = (r["_q_doc"], r["pos"]), (r["source"]["_q_doc"], r["source"]["pos"])
        assert source < here and common(here, source) >= r["n"]
        for k in range(r["n"]):
            covered[here[0], here[1] + k] = max(covered.get((here[0], here[1] + k), 0), r["n"] - k)
    # every later copy lies under a run, and the runs reach at least half the longest common prefix at its start
    assert set(covered) == {(d, p + k) for (d, p), n in longest.items() for k in range(n)}
    assert all(2 * covered[s] >= n for s, n in longest.items() if n)
    assert max(r["n"] for r in got) == max(longest.values())


# --- 4 -----------------------------------------------------------------------------------------------------------------


def slow_fingerprint(text):
    w = re.sub("[A-Z]", lambda m: m[0].lower(), text or "")
    w = re.findall(r"[^\x20\x09-\x0D]+", w)
    h = [xxhash.xxh64_intdigest(" ".join(w[i : i + 3]).encode(), 42) for i in range(max(1, len(w) - 2))] if w else []
    return sum(1 << b for b in range(64) if 2 * sum(x >> b & 1 for x in h) > len(h))


def test_fingerprints_and_classes(docs, empty):
    got = simhash.classes(docs).collect()
    rows = pairs(docs)
    assert len(got) == len(rows)
    fps = {t: slow_fingerprint(t) for _, t in rows}
    reach = {f: f for f in fps.values()}
    for _ in fps:
        for a, b in product(reach, reach):
            if (a ^ b).bit_count() <= 2:
                reach[a] = reach[b] = min(reach[a], reach[b])
    least = {}
    for d, t in rows:
        r = reach[fps[t]]
        least[r] = min([x for x in (least.get(r), d) if x is not None], default=None)
    assert sorted(((r["doc_id"], r["fp"] % 2**64, r["component_id"]) for r in got), key=str) == sorted(((d, fps[t], least[reach[fps[t]]]) for d, t in rows), key=str)
    assert simhash.classes(empty).count() == 0


def test_links_find_every_near_pair(spark):
    base = RNG.integers(0, 2**63, 60)
    near = [int(b) ^ (1 << int(k)) ^ (1 << int(j)) for b, k, j in zip(base, RNG.integers(0, 62, 60), RNG.integers(0, 62, 60), strict=True)]
    fps = sorted({*map(int, base), *near})
    edges = simhash.links(spark.createDataFrame([(f,) for f in fps], "fp bigint"))
    from quadpost.llm.components import stars

    got = {r["node"]: r["root"] for r in stars(edges).collect()}
    for a, b in product(fps, fps):
        if (a ^ b).bit_count() <= 2:
            assert got.get(a, a) == got.get(b, b)


def test_wide_classes(spark, empty):
    base = " ".join(f"w{x}" for x in RNG.integers(0, 5000, 300))
    changed = base.split()
    changed[7] = changed[150] = "other"
    rows = [(3, base), (1, " ".join(changed)), (2, " ".join(f"w{x}" for x in RNG.integers(0, 5000, 300))), (4, base), (5, "six words are very few here"), (6, "six other words stand right there")]
    got = {r["doc_id"]: r["component_id"] for r in simhash.wide_classes(spark.createDataFrame(rows, "doc_id bigint, text string")).collect()}
    assert got == {1: 1, 3: 1, 4: 1, 2: 2, 5: 5, 6: 6}
    assert simhash.wide_classes(empty).count() == 0


def test_wide_classes_link_by_exact_similarity(spark, monkeypatch):
    """Against all pairs: chains of ever less alike texts, and texts of one long word repetition with different ends."""
    monkeypatch.setattr(simhash, "CHECKED", 5)
    rng = np.random.default_rng(3)
    texts = [f"{'word ' * 300}{' '.join(f'w{x}' for x in rng.integers(0, 9000, 40))}" for _ in range(6)]
    for share in (0.004, 0.02, 0.03, 0.04, 0.06, 0.08):
        base = rng.integers(0, 9000, 250)
        texts += [" ".join(f"w{x}" for x in np.where(rng.random(250) < share, rng.integers(0, 9000, 250), base)) for _ in range(6)]
    sets = [{tuple(t.split()[i : i + 5]) for i in range(len(t.split()) - 4)} for t in texts]
    root = list(range(len(texts)))
    for i, j in product(range(len(texts)), repeat=2):
        if i < j and len(sets[i] & sets[j]) >= 0.8 * len(sets[i] | sets[j]):
            root = [root[i] if r == root[j] else r for r in root]
    want = {i: min(j for j, r in enumerate(root) if r == root[i]) for i in range(len(texts))}
    rows = [*enumerate(texts), (90, texts[0]), (90, texts[0])]
    got = {r["doc_id"]: r["component_id"] for r in simhash.wide_classes(spark.createDataFrame(rows, "doc_id bigint, text string")).collect()}
    assert got == {**want, 90: 0} and 6 < len(set(want.values())) < len(texts)
    kept = [r for r in simhash.wide_classes(spark.createDataFrame(rows, "doc_id bigint, text string")).collect() if r["keep"]]
    assert sorted({(r["doc_id"], r["row"]) for r in kept}) == sorted((r["doc_id"], r["row"]) for r in {r["row"]: r for r in kept}.values()) and {r["doc_id"] for r in kept} == set(want.values())
    assert simhash.wide_fingerprint("a b c d e " * 50) == simhash.wide_fingerprint("a b c d e " * 3)


@pytest.mark.parametrize("n", [5, 60, 400])
def test_bands_find_alike_sets(n):
    rng = np.random.default_rng(n)
    met, near, pairs = 0, 0, 300
    for _ in range(pairs):
        common = int(np.ceil(0.8 / 1.8 * 2 * n))
        a = rng.integers(0, 2**63, n).astype(np.uint64)
        b = np.concatenate([a[:common], rng.integers(0, 2**63, n - common).astype(np.uint64)])
        met += (simhash.band_keys(np.sort(a)) == simhash.band_keys(np.sort(b))).any()
        marks = [(simhash.majority(np.sort(x), True), simhash.majority(simhash._second(np.sort(x)), True)) for x in (a, b)]
        near += sum((p ^ q).bit_count() for p, q in zip(*marks, strict=True)) <= simhash.WIDE_RADIUS
    assert met >= pairs - 1 and near >= pairs - 1
    strange = [simhash.band_keys(np.sort(rng.integers(0, 2**63, n).astype(np.uint64))) for _ in range(100)]
    assert not any((x == y).any() for i, x in enumerate(strange) for y in strange[:i])


def test_links_of_small_and_large_groups(spark, monkeypatch):
    import pyarrow as pa

    rng = np.random.default_rng(6)
    out = []
    for key, size in ((1, 3), (2, 1), (5, 200), (9, 64), (11, 65), (12, 2)):
        for _ in range(size):
            base = rng.integers(-(2**62), 2**62, 2) if rng.random() < 0.3 or not out else out[int(rng.integers(0, len(out)))][5:]
            a, b = (int(x) ^ (1 << int(k)) for x, k in zip(base, rng.integers(0, 60, 2), strict=True))
            out.append((key, 0, 0, 0, len(out), a, b))
    table = pa.table({n: [r[i] for r in out] for i, n in enumerate(("key", "low", "high", "g", "id", "a", "b"))})
    got = [e for batch in simhash._compared(table, 6) for e in zip(*(batch.column(i).to_pylist() for i in (0, 1)), strict=True)]
    up = {i: i for i in range(len(out))}

    def root(i):
        return i if up[i] == i else root(up[i])

    brute = {(r[4], s[4]) for r in out for s in out if r[0] == s[0] and r[4] < s[4] and (r[5] ^ s[5]).bit_count() + (r[6] ^ s[6]).bit_count() <= 6}
    for u, v in got:
        assert out[u][0] == out[v][0]
        up[max(root(u), root(v))] = min(root(u), root(v))
    mine = [root(i) for i in range(len(out))]
    up = {i: i for i in range(len(out))}
    for u, v in brute:
        up[max(root(u), root(v))] = min(root(u), root(v))
    assert mine == [root(i) for i in range(len(out))] and len(set(mine)) < len(out)


def test_components_of_a_long_chain(spark):
    from quadpost.llm.components import stars

    edges = spark.createDataFrame([(i, i + 1) for i in range(200)] + [(500, 501)], "u bigint, v bigint")
    assert {(r["node"], r["root"]) for r in stars(edges).collect()} == {(i, 0) for i in range(1, 201)} | {(501, 500)}


# --- 5 -----------------------------------------------------------------------------------------------------------------


def test_nearest(spark):
    x = RNG.normal(size=(1500, 24))
    x /= np.linalg.norm(x, axis=1, keepdims=True)
    x[100:140] = x[99]
    rows = [(i, v.tolist(), 1) for i, v in enumerate(x)] + [(2000, None, 0), (2020, [0.0] * 24, 0), (2040, [float("nan")] + [1.0] * 23, 0), (2060, [None] + [1.0] * 23, 0), (2080, [1.0, 2.0], 0), (2081, [2.0, 1.0], 0), (None, [1.0] * 24, 0), (20, x[20].tolist(), 1)]
    df = spark.createDataFrame(rows, "vec_id bigint, embedding array<double>, rank int")
    got = neighbours.nearest(df, F.col("vec_id") % 20 == 0).collect()
    by = {}
    for r in got:
        by.setdefault(r["query_id"], []).append((r["rank"], r["vec_id"], r["score"]))
    assert set(by) == set(range(0, 1500, 20)) | {2080}
    assert sorted(by[2080]) == [(1, 2081, 4.0)]
    found = want = 0
    for q in range(0, 1500, 20):
        best = sorted(((-float((x[q] * x[i]).sum()), i) for i in range(1500) if i != q))[:20]
        mine = sorted(by[q])
        assert [r for r, _, _ in mine] == list(range(1, len(mine) + 1)) and len({i for _, i, _ in mine}) == len(mine)
        assert all(s == pytest.approx(float(x[q] @ x[i]), abs=1e-12) for _, i, s in mine)
        found += len({i for _, i, _ in mine} & {i for _, i in best})
        want += 20
    assert found / want >= 0.9
    assert [i for _, i, _ in sorted(by[100])] == [99, *range(101, 120)]


def test_nearest_of_uneven_lengths_in_blocks(spark):
    x = RNG.normal(size=(600, 16)) * RNG.uniform(0.2, 4, (600, 1))
    df = spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(x)], "vec_id bigint, embedding array<double>")
    got = neighbours.nearest(df, F.col("vec_id") % 20 == 0, k=5, block=9).collect()
    found = sum(r["vec_id"] in np.argsort(-(x @ x[r["query_id"]] - 1e9 * (np.arange(600) == r["query_id"])))[:5] for r in got)
    assert len(got) == 150 and found / 150 >= 0.9
    assert neighbours.nearest(df.limit(0), F.col("vec_id") % 20 == 0).count() == 0


@pytest.mark.parametrize("case", ["one long", "lognormal", "small", "few met"])
def test_nearest_of_any_lengths_is_whole(spark, case):
    rng = np.random.default_rng(5)
    n = 15 if case == "small" else 2000
    x = rng.normal(size=(n, 64))
    x /= np.linalg.norm(x, axis=1, keepdims=True)
    if case == "one long":
        x[7] *= 100
    if case == "lognormal":
        x *= rng.lognormal(size=(n, 1))
    df = spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(x)], "vec_id bigint, embedding array<double>")
    few = {"tables": 1, "probes": 1, "small": 0} if case == "few met" else {}
    got = neighbours.nearest(df, F.col("vec_id") % 20 == 0, **few).collect()
    by = {}
    for r in got:
        by.setdefault(r["query_id"], set()).add(r["vec_id"])
    for q in range(0, n, 20):
        best = [i for i in np.argsort(-(x @ x[q]), kind="stable").tolist() if i != q][:20]
        assert len(by[q]) == min(20, n - 1) and (case == "few met" or by[q] == set(best))


def test_tables_of_few_rows_are_searched_by_the_same_buckets(spark, monkeypatch):
    """No switch by size: 1200 rows are met by probes, more of them because the first ones meet too few rows."""
    x = np.random.default_rng(6).normal(size=(1200, 64))
    x /= np.linalg.norm(x, axis=1, keepdims=True)
    df = spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(x)], "vec_id bigint, embedding array<double>")
    made, build = [], neighbours.QueryBlock.__init__
    monkeypatch.setattr(neighbours.QueryBlock, "__init__", lambda self, ids, v, exact, tables, probes: made.append((exact, probes)) or build(self, ids, v, exact, tables, probes))
    got = neighbours.nearest(df, F.col("vec_id") % 20 == 0).collect()
    assert made == [(False, neighbours.PROBES), (False, neighbours.PROBES * neighbours.FURTHER)]
    best = {q: set([i for i in np.argsort(-(x @ x[q])).tolist() if i != q][:20]) for q in range(0, 1200, 20)}
    assert sum(r["vec_id"] in best[r["query_id"]] for r in got) >= 0.9 * 60 * 20


def test_hadamard_is_the_matrix_of_both_ways():
    x = RNG.normal(size=(5, 64))
    assert np.allclose(neighbours.hadamard(x), neighbours._butterflies(x)) and np.allclose(neighbours.hadamard(neighbours.hadamard(x)), 64 * x)
    hasher = neighbours.Hasher(50, 3)
    for y in hasher.turned(x[:, :50], 1):
        assert np.allclose((y**2).sum(axis=1), (x[:, :50] ** 2).sum(axis=1))
    assert (hasher.probes(x[:, :50], 2, 8)[:, 0] == hasher.bucket(x[:, :50], 2)).all()


def test_registered_tables_meet_few_pairs_and_find_most_neighbours(spark):
    """The registered parameters on 2000 given vectors, against brute force; so few are ranked exactly by the operator, and more rows have nearer neighbours."""
    rows = spark.read.parquet("/root/testdata/sf0.1/embeddings.parquet").orderBy("vec_id").collect()
    x = np.array([r["embedding"] for r in rows], np.float64)
    asked = np.arange(0, len(x), 20)
    block = neighbours.QueryBlock(asked, x[asked], False, neighbours.TABLES, neighbours.PROBES)
    met = block.meet(x)
    products = x[asked] @ x.T
    products[np.arange(len(asked)), asked] = -np.inf
    best = np.argsort(-products, axis=1)[:, :20]
    recall, share = np.take_along_axis(met, best, axis=1).mean(), met.mean()
    print(f"recall {recall:.3f}, pairs met {share:.3f}")
    assert recall >= 0.85 and share < 0.2


# --- 6 -----------------------------------------------------------------------------------------------------------------


def test_sharding(spark, docs, empty):
    got = sharding.assign_shards(docs, "doc_id", F.octet_length("text"), 3000)
    assert got.count() == docs.count() and {"lang", "prefix", "rank"} <= set(got.columns)
    size = {}
    for r in got.collect():
        size.setdefault((r["shard"], r["page"]), []).append(r)
    for rows in size.values():
        total = sum(r["n_bytes"] for r in rows)
        assert all(r["shard_bytes"] == total for r in rows) and (total <= 3000 or len(rows) == 1)
    names = sorted({s for s, _ in size})
    assert not any(b.startswith(a) and a != b for a, b in product(names, names))
    assert sharding.assign_shards(empty, "doc_id", F.octet_length("text"), 3000).count() == 0


def test_one_key_with_most_rows(spark):
    rows = spark.range(3000).select(F.when(F.col("id") < 2000, F.lit(7)).otherwise(F.col("id")).alias("k"), F.lit(10).alias("size"))
    got = sharding.assign_shards(rows, "k", F.col("size"), 500)
    sums = got.groupBy("shard", "page").agg(F.sum("n_bytes").alias("b")).collect()
    assert got.count() == 3000 and max(r["b"] for r in sums) <= 500


def test_sharding_plan_has_no_python(docs):
    plan = sharding.assign_shards(docs.select("doc_id", "text"), "doc_id", F.octet_length("text"), 1 << 20)._jdf.queryExecution().executedPlan().toString()
    assert not re.search("Python|Arrow|Pandas", plan)


# --- 7 -----------------------------------------------------------------------------------------------------------------


def brute_substrings(texts, window):
    split = lambda t: re.findall(r"[^\x20\x09-\x0D]+", t or "")
    low = lambda d: -1 if d is None else d
    first = {}
    for d, t in texts:
        w = split(t)
        for i in range(len(w) - window + 1):
            g = tuple(w[i : i + window])
            first[g] = min(first.get(g, 1 << 60), low(d))
    out = []
    for d, t in texts:
        w, gone = split(t), set()
        for i in range(len(w) - window + 1):
            if first[tuple(w[i : i + window])] < low(d):
                gone |= set(range(i, i + window))
        out.append((d, len(w), len(gone), hashlib.sha256(" ".join(x for i, x in enumerate(w) if i not in gone).encode()).hexdigest()))
    return sorted(out, key=str)


@pytest.mark.parametrize("common, chunk", [(1 << 20, 4 << 20), (1, 1), (50, 2000)])
def test_substring_dedup(spark, docs, empty, common, chunk):
    shared = prose(70)
    more = spark.createDataFrame([(100 + i, f"{prose(i)} {shared} {prose(7 * i)} {shared}") for i in range(12)] + [(200 + i, "word " * (900 + i)) for i in range(3)], "doc_id bigint, text string")
    every = docs.select("doc_id", "text").unionByName(more)
    got = substrings.dedup_substrings(every, 20, 5, common, chunk)
    assert sorted((tuple(r)[:4] for r in got.collect()), key=str) == brute_substrings(pairs(every), 20)
    assert substrings.dedup_substrings(empty).count() == 0


def test_common_grams_are_no_minimisers(spark):
    rng = np.random.default_rng(4)
    new = lambda n: " ".join(f"w{x}" for x in rng.integers(0, 10**9, n))
    passage = new(80)
    df = spark.createDataFrame([(i, f"{new(60)} {passage} {new(60)}") for i in range(40)], "doc_id bigint, text string")
    common = substrings.common_grams(df)
    assert set(common.tolist()) == set(substrings.grams(substrings.words(passage)).tolist())
    kinds = {}
    for r in df.collect():
        ws = substrings.words(r["text"])
        for start, n, mini in substrings.super_kmers(ws, common=common):
            kinds.setdefault(mini, set()).add(tuple(ws[start : start + n + 49]))
    assert max(map(len, kinds.values())) == 1


def test_one_word_again_and_again_is_cut_and_sorted_in_little_memory():
    import tracemalloc

    ws = [b"word"] * 1_000_000
    parts = substrings.super_kmers(ws)
    assert max(n for _, n, _ in parts) == substrings.MOST_WINDOWS and sum(n for _, n, _ in parts) == len(ws) - 49
    import pyarrow as pa

    rows = [(7, i, 0, i, n, b" ".join(ws[s : s + n + 49])) for i, (s, n, _) in enumerate(parts[:4000])]
    table = pa.Table.from_batches([substrings._batch(rows, substrings._PACKED)])
    tracemalloc.start()
    got = substrings._decided(table, 50)
    assert tracemalloc.get_traced_memory()[1] < 400e6
    tracemalloc.stop()
    assert got.column("first").to_pylist() == [0] * (len(rows) - 1) and got.column("last").to_pylist() == [n - 1 for _, _, _, _, n, _ in rows[1:]]


def test_super_kmers_cover_every_window_once():
    ws = substrings.words(prose(500))
    parts = substrings.super_kmers(ws)
    assert [s for s, _, _ in parts] == np.cumsum([0, *[n for _, n, _ in parts[:-1]]]).tolist() and sum(n for _, n, _ in parts) == len(ws) - 49


# --- 8 -----------------------------------------------------------------------------------------------------------------


@pytest.fixture(scope="module")
def plain():
    import public_tokenizers
    from tokenizers import Tokenizer

    reader = Tokenizer.from_file(public_tokenizers.path("byte_bpe_50k.json"))
    return lambda text: reader.encode(text, add_special_tokens=False).ids


ODD_TEXTS = ["", " ", "a  b", "a   b", "   ", "\n\n x", " 　 z", "a\n  b", "a \n b", "a\t b \t", "x\x1c y", "x \x1dy", "x\x85 y", "<|endoftext|>", "stop <|endoftext|> go", "stop  <|endoftext|>  go", "<|endoftext|><|endoftext|>", "<|endoftext", "it's we'LL 'S 's", " 's x", "x" * 3000, "日本語 テスト 🎉🎉", "é ñ̃", "1234 5,678.90", "\t\t\ttab", "a\r\nb \r\n", "…—“”", "\x00\x01", "a ​ b", "a \xa0b"]


def test_ids_are_those_of_the_plain_call(spark, plain):
    texts = ODD_TEXTS + [r["text"] for r in spark.read.parquet(f"{SMALL}/documents.parquet").collect()]
    ours = tokens.Encoder(tokens.default_path())
    for t in texts * 2:
        assert ours.ids(t).tolist() == plain(t)
    assert ours.ids("stop <|endoftext|> go").tolist() == [11338, 220, 50256, 467]


@pytest.mark.parametrize("text", [f"a{' ' * 1_000_000}b", "a" + "\n" * 1_000_000, "x" * 1_000_000, "日" * 300_000, "a b" * 300_000, "x " * 300_000])
def test_ids_of_very_long_runs(plain, text):
    assert tokens.Encoder(tokens.default_path()).ids(text).tolist() == plain(text)


@settings(max_examples=400, deadline=None)
@given(st.text(st.one_of(st.sampled_from(" \t\n\r\x0b\x1c\x85\u3000\u200b a1'.é<|"), st.characters(exclude_categories=("Cs",))), max_size=30))
def test_ids_of_any_text(plain, text):
    ours = tokens.encoder(tokens.default_path())
    assert ours.ids(text).tolist() == plain(text)


def test_ids_of_latin_letters(plain):
    ours = tokens.encoder(tokens.default_path())
    letters = [chr(c) for c in range(0x20, 0x260)]
    for text in (" ".join(letters), " ".join(f"a{c}b." for c in letters), "".join(letters), "so Word, word; WORD: été! straße? naïve... l'eau, x.. don't. ªº µm, ĳ ǆ."):
        assert ours.ids(text).tolist() == plain(text)


def test_a_word_is_read_once_whatever_stands_beside_it(plain, monkeypatch):
    ours, read = tokens.Encoder(tokens.default_path()), []
    word = ours._word
    monkeypatch.setattr(ours, "_word", lambda letters, before=" ": read.append((letters, before)) or word(letters, before))
    for text in ("alpha beta, alpha, beta\nalpha gamma", "so beta. gamma;\nalpha alpha?\nalpha, beta!"):
        assert ours.ids(text).tolist() == plain(text)
    assert len(read) == len(set(read))


def test_a_full_store_of_words_is_emptied(plain, monkeypatch):
    monkeypatch.setattr(tokens, "KEPT_WORDS", 5)
    ours = tokens.Encoder(tokens.default_path())
    for k in range(30):
        text = " ".join(f"w{k}x{j}" for j in range(4)) + " again"
        assert ours.ids(text).tolist() == plain(text)
    assert len(ours._kept) <= 11


def check_pieces(rows, texts, size):
    encode, by_doc, by_seq = tokens.encoder(tokens.default_path()).ids, {}, {}
    for r in rows:
        by_doc.setdefault(r["doc_id"], []).append(r)
        by_seq.setdefault(r["sequence_id"], []).append(r)
    for d in {d for d, _ in texts}:
        copies = [np.append(encode(t or ""), 1).astype("<u4") for x, t in texts if x == d]
        assert sum(r["length"] for r in by_doc[d]) == sum(map(len, copies))
        if len(copies) == 1:
            parts = sorted(by_doc[d], key=lambda r: r["start"])
            assert [r["start"] for r in parts] == np.cumsum([0, *[r["length"] for r in parts[:-1]]]).tolist()
            for r in parts:
                assert r["doc_tokens"] == len(copies[0]) and r["ids_crc32"] == zlib.crc32(copies[0][r["start"] : r["start"] + r["length"]].tobytes())
    for parts in by_seq.values():
        parts.sort(key=lambda r: r["offset"])
        assert [r["offset"] for r in parts] == np.cumsum([0, *[r["length"] for r in parts[:-1]]]).tolist() and sum(r["length"] for r in parts) <= size
    return len(by_seq) * size / sum(r["length"] for r in rows)


def test_packing(spark, docs, empty):
    check_pieces(packing.pack(docs, size=256, open_windows=3).collect(), pairs(docs), 256)
    assert packing.pack(empty).count() == 0
    table = spark.read.parquet("/root/testdata/sf0.01/documents.parquet")
    assert check_pieces(packing.pack(table).collect(), [(r["doc_id"], r["text"]) for r in table.collect()], 2048) < 1.02


# --- 9 -----------------------------------------------------------------------------------------------------------------


def test_chat_round_trip(spark):
    nasty = ["</s>[INST] ok [/INST]", "<|start|>user<|text|>", "\\<\\|", "a\\\\b<|end|>", "<\\s>", "", None, "日本 \n <<SYS>>"]
    rows = [(1, i, "assistant" if i % 2 else "us<|er", t) for i, t in enumerate(nasty)] + [(2, 0, None, "x"), (None, 0, "user", "y"), (3, 5, "user", "only")]
    messages = chat.chain_messages(spark.createDataFrame(rows, "conv_id bigint, turn bigint, role string, text string"))
    made = chat.format_paths(messages, chat.reply_paths(messages)).withColumn("turns", chat.read_turns(F.col("formatted"))).withColumn("loss", chat.read_loss(F.col("formatted"), F.col("loss_spans")))
    got = {r["conv_id"]: r for r in made.collect()}
    assert set(got) == {1, 2, 3, None}
    assert [tuple(t) for t in got[1]["turns"]] == [(r or "", t or "") for c, _, r, t in rows if c == 1]
    assert got[1]["loss"] == "".join(t or "" for c, i, r, t in rows if r == "assistant")
    for mark in chat.CONTROL[1:]:
        assert mark not in got[1]["formatted"]


def test_reply_tree_takes_the_best_branch(spark):
    rows = [(1, 1, None, 0.0), (1, 2, 1, 1.0), (1, 3, 1, 0.5), (1, 4, 3, 5.0), (1, 5, 2, 1.0), (1, 6, 99, 0.1), (2, 1, 2, 0.0), (2, 2, 1, 0.0), (3, 9, None, None)]
    m = spark.createDataFrame(rows, "conv_id bigint, msg_id bigint, parent_id bigint, score double").withColumn("role", F.lit("user")).withColumn("text", F.col("msg_id").cast("string"))
    best = {r["conv_id"]: (r["path"], r["score"]) for r in chat.reply_paths(m).collect()}
    assert best == {1: ([1, 3, 4], 5.5), 3: ([9], 0.0)}
    ranked = sorted((r["rank"], r["path"]) for r in chat.reply_paths(m, best=3).where("conv_id = 1").collect())
    assert ranked == [(1, [1, 3, 4]), (2, [1, 2, 5]), (3, [6])]
    assert chat.format_paths(m.limit(0), chat.reply_paths(m.limit(0))).count() == 0


def test_long_chains_equal_ids_and_clashing_columns(spark):
    long = [(1, i, i - 1 if i else None, "user", f"t{i}", 0.5, "x", 0) for i in range(300)]
    rows = long + [(2, 1, None, "user", "b", 0.0, "x", 0), (2, 1, None, "user", "a", 0.0, "y", 1), (2, 2, 1, "assistant", None, 1.0, None, None), (2, 2, 1, "assistant", "c", 2.0, None, None), (None, 5, None, None, None, None, None, None)]
    m = spark.createDataFrame(rows, "conv_id bigint, msg_id bigint, parent_id bigint, role string, text string, score double, top string, steps int")
    paths = chat.reply_paths(m)
    got = {r["conv_id"]: (r["path"], r["score"]) for r in paths.collect()}
    assert got == {1: (list(range(300)), 150.0), 2: ([1, 2], 2.0), None: ([5], 0.0)}
    made = {r["conv_id"]: r["formatted"] for r in chat.format_paths(m, paths).collect()}
    assert made[1].count(chat.START) == 300 and made[2] == f"{chat.START}user{chat.TEXT}a{chat.END}{chat.START}assistant{chat.TEXT}{chat.END}"


def test_chat_plan_has_no_python(spark):
    plan = queries.op9_chat_formatting(spark, SMALL)._jdf.queryExecution().executedPlan().toString()
    assert not re.search("Python|Arrow|Pandas", plan)


# --- 10 ----------------------------------------------------------------------------------------------------------------


def test_language_of_held_out_rows(spark):
    d = spark.read.parquet("/root/testdata/sf0.01/documents.parquet")
    got = language.predict(d, language.fit(d)).join(d.select("doc_id", "lang"), "doc_id").where(language.held_out(F.col("doc_id"))).collect()
    assert len(got) > 100 and np.mean([r["lang_pred"] == r["lang"] for r in got]) > 0.95 and all(0 <= r["score"] <= 1 for r in got)


def test_odd_texts_have_no_language(spark, docs, empty):
    model = language.train([("the quick brown fox and the dog", "en"), ("der schnelle braune Fuchs und der Hund", "de")] * 5)
    got = [(r["doc_id"], r["lang_pred"]) for r in language.predict(docs, model).collect()]
    assert len(got) == docs.count() and all(p == "und" for d, p in got if d in (0, 1, 2, 16)) and all(p != "und" for d, p in got if d in (3, 4, 6))
    assert language.predict(docs, language.fit(empty)).where("lang_pred != 'und'").count() == 0
    assert language.keep_accepted(docs, model).columns == docs.columns


UNLEARNED = [
    "Nel mezzo del cammin di nostra vita mi ritrovai per una selva oscura, che la diritta via era smarrita. Il governo ha deciso ieri che la nuova legge sarà discussa dal parlamento.",
    "Wczoraj wieczorem poszliśmy do kina, aby obejrzeć nowy film, który wszyscy bardzo chwalili.",
    "Eilen illalla menimme elokuviin katsomaan uutta elokuvaa, jota kaikki olivat kehuneet.",
    "Gisteravond gingen we naar de bioscoop om de nieuwe film te zien die iedereen zo geprezen had.",
    "Вчера вечером мы пошли в кино, чтобы посмотреть новый фильм.",
    "昨天晚上我们去电影院看了一部新电影",
    "xkcd qwrtz bvnmp lkjhg fdsqw zxcvb",
]


@pytest.mark.parametrize("known", [("de", "en", "es", "fr"), ("en", "fr"), ("en",)])
def test_texts_in_unlearned_languages_go(spark, known):
    d = spark.read.parquet("/root/testdata/sf0.01/documents.parquet").where(F.col("lang").isin(*known)).cache()
    model = language.fit(d)
    assert list(known) == model.languages and not any(model.judge(t)[2] for t in UNLEARNED)
    assert language.keep_accepted(d, model).count() > 0.95 * d.count()
    assert language.keep_accepted(spark.createDataFrame([(i, t) for i, t in enumerate(UNLEARNED)], "doc_id bigint, text string"), model).count() == 0
    long = {lang: [r["text"] for r in d.where((F.col("lang") == lang) & (F.length("text") > 1500)).orderBy("doc_id").limit(10).collect()] for lang in (known[0], known[-1])}
    split = [a[:800] + "\n" + b[:800] for a, b in zip(long[known[0]], long[known[-1]], strict=True)]
    assert np.mean([model.judge(t)[2] for t in split]) >= 0.9
