"""Each operator against a brute-force version on a small table with nulls, empty and repeated rows."""

import math
import random
import re
import zlib
from collections import Counter

import numpy as np
import pytest
from pyspark.sql import functions as F

from hybridsort.llm import components, decontam, htmltext, language, neardup, packing, quality, sharding, suffix_array, suffix_tree, toxicity

WORDS = [f"w{i}" for i in range(60)] + ["Straße", "naïve", "É", "x"]
SCHEMA = "doc_id long, text string, lang string, source string, n_chars long, kept boolean, n_words long, shard string, spans string"


def words(n, rng):
    return " ".join(rng.choice(WORDS) for _ in range(n))


def corpus():
    rng = random.Random(3)
    shared = words(60, rng)
    texts = [words(rng.randrange(0, 200), rng) for _ in range(30)]
    texts += [texts[3], texts[3], texts[4] + " tail", shared + " " + words(40, rng), words(50, rng) + "\n" + shared, "ab" * 300, "ab" * 300 + "c", "word " * 90]
    texts += [None, "", "  \n\t ", "one", "two words", "<|endoftext|> a  b<|endoftext|>", "x" * 5000]
    near = texts[5].split()
    texts.append(" ".join(near[:-1] + ["changed"]))
    rows = [(i, t) for i, t in enumerate(texts)]
    return rows + [(3, texts[3]), (None, "no id " + words(80, rng)), (None, None)]


ROWS = corpus()


@pytest.fixture(scope="module")
def docs(spark):
    # further columns carry names that the operators use themselves
    return spark.createDataFrame([(i, t, "en" if k % 3 else None, "s", None if t is None else len(t), None, 7, "a", "b") for k, (i, t) in enumerate(ROWS)], SCHEMA).repartition(3).cache()


@pytest.fixture(scope="module")
def empty(spark):
    return spark.createDataFrame([], SCHEMA)


def ids(text):
    from public_tokenizers import path
    from tokenizers import Tokenizer

    tok = ids.tok = getattr(ids, "tok", None) or Tokenizer.from_file(path("byte_bpe_50k.json"))
    return tok.encode(text or "", add_special_tokens=False).ids + [0]


@pytest.mark.parametrize("windows,fan_in", [(2, 2), (32, 64)])
def test_packing_round_trip(docs, windows, fan_in):
    rows = packing.pack(docs, size=128, open_windows=windows, fan_in=fan_in).collect()
    by = {}
    for r in rows:
        got = np.frombuffer(r["ids"], np.uint32)
        assert len(got) == r["length"] and zlib.crc32(r["ids"]) == r["ids_crc32"]
        by.setdefault(r["sequence_id"], []).append((r["offset"], r["length"]))
    used = 0
    for pieces in by.values():
        at = 0
        for offset, length in sorted(pieces):
            assert offset == at
            at += length
        assert at <= 128
        used += at
    assert used == sum(len(ids(t)) for _, t in ROWS)
    assert len(by) <= -(-used // 128) * 1.15 + 1
    for key, text in ROWS:
        if key is not None and key != 3:
            own = sorted((r["start"], bytes(r["ids"])) for r in rows if r["doc_id"] == key)
            assert np.frombuffer(b"".join(b for _, b in own), np.uint32).tolist() == ids(text)


def brute_components(rows, width, percent):
    def shingles(t):
        w = re.findall(r"[^\x20\x09-\x0D]+", (t or "").translate({c: c + 32 for c in range(65, 91)}))
        return {tuple(w[i : i + width]) for i in range(len(w) - width + 1)} or ({tuple(w)} if w else set())

    sets = [(i, shingles(t)) for i, t in rows if i is not None]
    parent = {i: i for i, _ in sets}

    def root(x):
        while parent[x] != x:
            x = parent[x]
        return x

    for a, x in sets:
        for b, y in sets:
            if x and y and 100 * len(x & y) >= percent * len(x | y):
                p, q = sorted((root(a), root(b)))
                parent[q] = p
    return {(i, len(s), root(i)) for i, s in sets}


@pytest.mark.parametrize("width,percent", [(3, 85), (5, 80)])
def test_neardup(docs, width, percent):
    got = neardup.link(docs, width, percent).collect()
    assert len(got) == len(ROWS)
    assert {(r["doc_id"], r["n_shingles"], r["component_id"]) for r in got if r["doc_id"] is not None} == brute_components(ROWS, width, percent)
    assert all(r["kept"] == (r["doc_id"] == r["component_id"]) for r in got if r["doc_id"] is not None)
    assert all(r["kept"] for r in got if r["doc_id"] is None)


def test_neardup_group_of_varied_copies(spark):
    rng = random.Random(1)
    base = [f"v{i}" for i in range(120)]
    rows = []
    for i in range(120):
        own = list(base)
        for _ in range(rng.randrange(0, 12)):
            own[rng.randrange(120)] = rng.choice(["p", "q", "r", f"u{i}"])
        rows.append((i, " ".join(own)))
    got = neardup.link(spark.createDataFrame(rows, "doc_id long, text string"), 3, 85).collect()
    assert {(r["doc_id"], r["n_shingles"], r["component_id"]) for r in got} == brute_components(rows, 3, 85)


def test_texts_of_a_shared_id(spark):
    rng = random.Random(16)
    a, b, c = (words(80, rng) for _ in range(3))
    rows = [(1, a), (1, b), (1, b), (2, a + " x"), (3, b + " y"), (4, c), (None, c)]
    df = spark.createDataFrame(rows, "doc_id long, text string")
    got = {r["doc_id"]: r["component_id"] for r in neardup.link(df, 3, 85).collect() if r["doc_id"] is not None}
    assert got == {1: 1, 2: 1, 3: 1, 4: 4}
    from hybridsort.llm import stages

    kept = stages.minhash_dedup(spark, df, "")
    assert sorted(((r["doc_id"], r["text"]) for r in kept.collect()), key=repr) == sorted([(1, a), (1, b), (4, c), (None, c)], key=repr)


def test_components(spark):
    rng = random.Random(5)
    edges = [(rng.randrange(300), rng.randrange(300)) for _ in range(260)] + [(400 + i, 401 + i) for i in range(60)]
    parent = list(range(500))

    def root(x):
        while parent[x] != x:
            x = parent[x]
        return x

    for a, b in edges:
        p, q = sorted((root(a), root(b)))
        parent[q] = p
    got = {r["node"]: r["component"] for r in components.components(spark.createDataFrame(edges, "a long, b long")).collect()}
    assert got == {n: root(n) for e in edges if e[0] != e[1] for n in e}


def test_sharding(docs):
    rows = sharding.shard(docs.select("doc_id", "text", "shard"), shards=4, block_rows=7).collect()
    assert len(rows) == len(ROWS)
    by = {}
    for r in rows:
        by.setdefault(r["shard"], []).append(r["slot"])
    sizes = [len(s) for s in by.values()]
    assert max(sizes) - min(sizes) <= 1 and len(by) == 4
    assert all(sorted(s) == list(range(len(s))) for s in by.values())


def test_communication_matrix_sums():
    counts, capacity = np.array([5, 0, 12, 3, 20]), np.array([10, 10, 9, 11])
    rows = [sharding.matrix_row(counts, sharding.roots(counts, capacity, 1), p, 1) for p in range(5)]
    assert np.sum(rows, 0).tolist() == capacity.tolist() and np.sum(rows, 1).tolist() == counts.tolist()
    mean = np.mean([sharding.matrix_row(counts, sharding.roots(counts, capacity, s), 4, s) for s in range(400)], 0)
    assert np.abs(mean - 20 * capacity / 40).max() < 0.3


def test_large_draws_follow_the_hypergeometric_law(monkeypatch):
    """By halving down to nothing, against the exact probabilities."""
    monkeypatch.setattr(sharding, "SMALL", 1)
    rng = np.random.default_rng(3)
    good, bad, n, rounds = 6, 9, 7, 20_000
    found = Counter(sharding.hypergeometric(rng, good, bad, n) for _ in range(rounds))
    off = 0.0
    for k in range(n + 1):
        p = math.comb(good, k) * math.comb(bad, n - k) / math.comb(good + bad, n)
        assert found[k] == 0 or p > 0
        off += (found[k] - rounds * p) ** 2 / (rounds * p) if p else 0
    assert off < 30  # chi-square with six degrees of freedom
    counts, capacity = np.array([5, 0, 12, 3, 20]), np.array([10, 10, 9, 11])
    nodes = sharding.roots(counts, capacity, 1)
    rows = [sharding.matrix_row(counts, nodes, p, 1) for p in range(5)]
    assert np.sum(rows, 0).tolist() == capacity.tolist() and np.sum(rows, 1).tolist() == counts.tolist()


def test_draws_of_many_rows():
    rng = np.random.default_rng(5)
    got = [sharding.hypergeometric(rng, 10**12, 3 * 10**12, 10**10) for _ in range(200)]
    spread = math.sqrt(10**10 * 0.25 * 0.75)
    assert abs(np.mean(got) - 25 * 10**8) < 4 * spread / math.sqrt(200) * 1.2
    assert 0.8 * spread < np.std(got) < 1.2 * spread
    out = sharding.draw(rng, np.array([10**12, 5, 2 * 10**12]), 10**11)
    assert int(out.sum()) == 10**11 and 0 <= out[1] <= 5


def test_every_order_is_as_likely(spark, tmp_path):
    """All placements of four rows in two shards, over many seeds."""
    df = spark.createDataFrame([(i, "") for i in range(4)], "doc_id long, text string").repartition(2)
    df.write.parquet(f"{tmp_path}/rows")
    df = spark.read.parquet(f"{tmp_path}/rows")
    found = Counter(tuple(r["doc_id"] for r in sorted(sharding.shard(df, 2, seed=s).collect(), key=lambda r: (r["shard"], r["slot"]))) for s in range(48))
    assert len(found) > 14 and max(found.values()) < 9

HTML = [
    ("<p>a<p>b", "a\n\nb"),
    ("<ul><li>x<li>y<ol start=4><li>z</ol></ul>", "- x\n- y\n  4. z"),
    ("<table><tr><th>Name<th>N<tr><td>Jo<td>1<tr><td>Zoë &amp; co<td>22</table>", "Name     | N\nJo       | 1\nZoë & co | 22"),
    ("a<script>if (x<y) {}</script><style>p{}</style><!-- c -->b", "ab"),
    ("a<div hidden>no</div><span style='display:none'>no</span> b", "a b"),
    ("<div style='visibility:hidden'>no<span style='visibility:visible'>yes</span></div>", "yes"),
    ("<pre>  k\n   v</pre>", "  k\n   v"),
    ("one<br>two", "one\ntwo"),
    ("<head><title>t</title></head><body>x  y\n z", "x y z"),
    ("", ""),
    (None, None),
    ("a < b &copy; <b>c</b>", "a < b © c"),
    ("<div>" * 2000 + "deep", "deep"),
    ("<!-- open", ""),
    ("<dialog>no</dialog><dialog open>yes</dialog>", "yes"),
    ("<details><summary>s</summary>no</details><details open><summary>t</summary>yes</details>", "s\nt\nyes"),
    ("<svg><title>no</title><text>drawn</text></svg> <math><mi>x</mi><annotation>no</annotation></math>", "drawn x"),
    ("<select><option>a<option>b</select>", "a\nb"),
    ("<table><tr><td rowspan=2>a<td>b<tr><td>c<tr><td>d<td>e</table>", "a | b\n  | c\nd | e"),
    ("<table><tr><td colspan=2>ab<td>c<tr><td>d<td>e<td>f</table>", "ab |   | c\nd  | e | f"),
    ("<table><tbody>loose<tr><td>x</table>", "loose\nx"),
    ("<table><form><tr><td>x</td></tr></form></table>", "x"),
    ("<table><tr><td colspan=900>x</table>", "x"),
    ("<a title='x>y'>in</a> <b title=\"z>out</b>", "in out"),
    ("<a x='>1</a><a>2</a>", "12"),
    ("a <b", "a <b"),
    ("<SCRIPT>x</SCRIPT ><TEXTAREA> t </TEXTAREA>", " t"),
]


@pytest.mark.parametrize("html,text", HTML)
def test_html(html, text):
    assert htmltext.extract(html) == text


@pytest.mark.parametrize("piece", ["<a ", "<a '", "<a \"x' ", "<", "<!", "<div><", "<a b='>", "</"])
def test_html_takes_time_in_proportion(piece):
    import time

    times = []
    for n in (20_000, 200_000):
        began = time.perf_counter()
        htmltext.extract(piece * n)
        times.append(time.perf_counter() - began)
    assert times[1] < 40 * max(times[0], 0.05)


def test_html_frame(spark):
    df = spark.createDataFrame([(i, h, "old") for i, (h, _) in enumerate(HTML)], "page_id long, html string, text string")
    assert {r["page_id"]: r["text"] for r in htmltext.render(df).collect()} == {i: t for i, (_, t) in enumerate(HTML)}


def brute_hits(text, items, window=10):
    w = decontam.normal_words(text)
    hit, found = set(), set()
    for item, t in items:
        v = decontam.normal_words(t)
        size = min(window, len(v))
        wins = {tuple(v[i : i + size]) for i in range(len(v) - size + 1)} if size else set()
        for i in range(len(w) - size + 1 if size else 0):
            if tuple(w[i : i + size]) in wins:
                hit |= set(range(i, i + size))
                found.add(item)
    return len(w), hit, sorted(found)


ITEMS = [(1, " ".join(ROWS[5][1].split()[10:35])), (2, "two words"), (3, ""), (4, None), (5, "zzz"), (6, " ".join(ROWS[6][1].split()[3:14]).upper()), (7, "word word word")]


@pytest.mark.parametrize("block", [4, 500_000])
def test_decontamination(spark, docs, block):
    bench = spark.createDataFrame(ITEMS, "item_id long, text string")
    got = decontam.find(docs, bench, block_words=block).collect()
    assert len(got) == len(ROWS)
    want = sorted((brute_hits(t, ITEMS) for _, t in ROWS), key=repr)
    have = sorted(((r["n_words"], {k for s in r["hit_spans"] for k in range(s["first"], s["past"])}, list(r["hit_items"])) for r in got), key=repr)
    assert have == want
    cleaned = decontam.clean(docs, bench)
    assert cleaned.columns == docs.columns
    assert all(not brute_hits(r["text"], [i for i in ITEMS if i[0] in (1, 6)])[1] for r in cleaned.collect())


def brute_words(rows, length):
    own = [(t or "").encode().split() for _, t in rows]
    seen = {}
    for w in own:
        for i in range(len(w) - length + 1):
            seen[tuple(w[i : i + length])] = seen.get(tuple(w[i : i + length]), 0) + 1
    out = []
    for (key, _), w in zip(rows, own):
        gone = {k for i in range(len(w) - length + 1) if seen[tuple(w[i : i + length])] > 1 for k in range(i, i + length)}
        out.append((key, len(w), len(gone), b" ".join(x for k, x in enumerate(w) if k not in gone)))
    return sorted(out, key=repr)


@pytest.mark.parametrize("often", [50_000, 2])
def test_suffix_tree(docs, often, monkeypatch):
    from hybridsort.llm import repeats

    monkeypatch.setattr(repeats, "OFTEN", often)
    got = suffix_tree.dedup(docs, 35).collect()
    assert sorted(((r["doc_id"], r["n_units"], r["n_removed"], bytes(r["kept_bytes"])) for r in got), key=repr) == brute_words(ROWS, 35)
    assert suffix_tree.clean(docs).columns == docs.columns


def brute_bytes(rows, length):
    order = sorted({(-1 if k is None else k, t or "") for k, t in rows})
    seen, out = set(), {}
    for key, t in order:
        b = t.encode()
        gone = bytearray(len(b))
        for i in range(len(b) - length + 1):
            if b[i : i + length] in seen:
                gone[i : i + length] = b"\1" * length
            seen.add(b[i : i + length])
        out[key, t] = (len(b), sum(gone), len(re.findall(b"\1+", bytes(gone))), bytes(c for c, g in zip(b, gone) if not g))
    return sorted(((k, *out[-1 if k is None else k, t or ""]) for k, t in rows), key=repr)


@pytest.mark.parametrize("often", [50_000, 2])
def test_suffix_array(docs, often, monkeypatch):
    from hybridsort.llm import repeats

    monkeypatch.setattr(repeats, "OFTEN", often)
    got = suffix_array.dedup(docs, 100).collect()
    assert sorted(((r["doc_id"], r["n_units"], r["n_removed"], r["n_spans"], bytes(r["kept_bytes"])) for r in got), key=repr) == brute_bytes(ROWS, 100)


def test_tree_nodes_are_the_maximal_repeats():
    rng = random.Random(3)
    for _ in range(60):
        parts = [np.array([rng.randrange(2) for _ in range(rng.randrange(0, 30))], np.int64) for _ in range(rng.randrange(1, 5))]
        tree = suffix_tree.SuffixTree(parts)
        places = {}
        for k, s in enumerate(parts):
            for i in range(len(s)):
                for j in range(i + 1, len(s) + 1):
                    places.setdefault(tuple(s[i:j].tolist()), []).append((k, i))

        def sides(found, size):
            left = [parts[k][i - 1] if i else -1 - k for k, i in found]
            right = [parts[k][i + size] if i + size < len(parts[k]) else -1 - k for k, i in found]
            return len(set(left)) > 1 and len(set(right)) > 1

        want = sorted((list(w), sorted(int(tree.starts[k]) + i for k, i in at)) for w, at in places.items() if len(w) >= 3 and len(at) > 1 and sides(at, len(w)))
        assert sorted(tree.maximal_repeats(3)) == want
        for k, s in enumerate(parts):
            for i in range(len(s)):
                longest = max((j for j in range(len(s) - i + 1) if len(places.get(tuple(s[i : i + j].tolist()), [])) > 1), default=0)
                assert tree.parents()[tree.starts[k] + i] == longest


def test_rows_without_id_are_told_apart_by_whole_digests(spark):
    rng = random.Random(12)
    rows = [(None, f"{i} " + words(60, rng)) for i in range(300)] + [(None, None), (7, words(50, rng)), (7, words(50, rng))]
    got = suffix_tree.dedup(spark.createDataFrame(rows, "doc_id long, text string")).collect()
    assert sorted(((r["doc_id"], r["n_units"], r["n_removed"], bytes(r["kept_bytes"])) for r in got), key=repr) == brute_words(rows, 35)


def test_permuted_common_prefixes():
    rng = random.Random(4)
    for _ in range(200):
        x = bytes(rng.choice(b"ab") for _ in range(rng.randrange(1, 80)))
        order = sorted(range(len(x)), key=lambda i: x[i:])
        got = suffix_array.permuted_common_prefixes(np.frombuffer(x, np.uint8), np.array(order), 20)
        for a, b in zip(order, order[1:]):
            same = next((k for k in range(21) if k == 20 or x[a + k : a + k + 1] != x[b + k : b + k + 1] or max(a, b) + k >= len(x)), 20)
            assert got[b] == same
        assert got[order[0]] == 0


def test_induced_sorting():
    rng = random.Random(2)
    for _ in range(300):
        n, k = rng.randrange(1, 90), rng.choice([1, 2, 3, 256])
        x = np.array([rng.randrange(k) for _ in range(n)], np.uint8)
        assert suffix_array.suffix_array(x).tolist() == sorted(range(n), key=lambda i: x.tobytes()[i:])


def test_quality(docs):
    rows = quality.judge(docs).collect()
    assert len(rows) == len(ROWS)
    want = []
    for key, t in ROWS:
        t = t or ""
        w = re.findall(r"[^\x20\x09-\x0D]+", t)
        lines = [x for x in t.split("\n") if x.strip(" \t\n\v\f\r")]
        tri = [tuple(w[i : i + 3]) for i in range(len(w) - 2)]
        rep = {k for i, x in enumerate(tri) if tri.count(x) > 1 for k in range(i, i + 3)}
        want.append((key, len(w), sum(map(len, w)), sum(c in "#*$%&|<>" for c in t), len(lines) - len(set(lines)), len(rep), len(w) < 50 or 100 * len(rep) > 50 * len(w)))
    names = ("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed")
    assert sorted((tuple(r[c] for c in names) for r in rows), key=repr) == sorted(want, key=repr)
    assert not any(r["kept"] for r in rows if r["base_failed"])


def test_kneser_ney_sums_to_one():
    data = (b"the cat sat on the mat and the dog ran off with a hat " * 3)
    grams, n = np.unique(quality.packed_grams(data), return_counts=True)
    model = quality.KneserNey(grams, n)
    for context in list(model.contexts[3][:20]) + [123456]:
        every = (int(context) << 6) | np.arange(64)
        assert abs(np.exp2(-model.bits(every)).sum() - 1) < 1e-9


def test_perplexity_rejects_noise(spark):
    rng = random.Random(4)
    rows = [(i, words(120, rng) + f" q{i}", "en") for i in range(60)]
    rows += [(100, " ".join("".join(chr(rng.randrange(33, 126)) for _ in range(9)) for _ in range(120)), "en")]
    got = {r["doc_id"]: r["kept"] for r in quality.judge(spark.createDataFrame(rows, "doc_id long, text string, lang string")).collect()}
    assert not got[100] and sum(got[i] for i in range(60)) >= 57


def test_copies_do_not_narrow_the_band(spark):
    rng = random.Random(9)
    rows = [(i, words(120, rng), "fr") for i in range(40)]
    rows += [(100 + i, rows[0][1], "fr") for i in range(200)]
    same = words(80, rng)
    rows += [(400, same, "de"), (401, same, "de"), (402, same + " " + same.split()[0], "de")]
    got = {r["doc_id"]: r["kept"] for r in quality.judge(spark.createDataFrame(rows, "doc_id long, text string, lang string")).collect()}
    assert sum(got[i] for i in range(40)) >= 38 and got[100] == got[0]
    assert got[400] and got[401] and got[402]


def brute_quality(rows):
    """Scores and verdicts of rows (id, text, lang), pair by pair and text by text."""
    own, byte_bits, models = {}, {}, {}
    for lang in {x or "" for _, _, x in rows}:
        grams = Counter(int(g) for _, t, x in rows if (x or "") == lang for g in quality.packed_grams((t or "").encode() + b"\n\n\n"))
        models[lang] = quality.KneserNey(np.array(list(grams)), np.array(list(grams.values())))
    for i, t, lang in rows:
        raw = (t or "").encode()
        byte_bits[i] = models[lang or ""].bits(quality.packed_grams(raw)) if raw else np.zeros(0)
        cut = []
        for m in re.finditer(rb"[^\x20\x09-\x0D]+", raw.lower()):
            word = b" " + m[0]
            cut += [(max(m.start() + 4 * k - (k > 0), m.start()), word[4 * k : 4 * k + 4]) for k in range(-(-len(word) // 4))]
        ends = [at for at, _ in cut[1:]] + [len(raw)] if cut else []
        own[i] = [((cut[k - 1][1] if k else b""), piece, byte_bits[i][at:end].sum()) for k, ((at, piece), end) in enumerate(zip(cut, ends, strict=True))]
    out = {}
    for lang in models:
        mine = [i for i, _, x in rows if (x or "") == lang]
        every = Counter(p[:2] for i in mine for p in own[i])
        cuts = (0, *quality.discounts(*(sum(n == k for n in every.values()) for k in (1, 2, 3, 4))))
        for i in mine:
            left = every - Counter(p[:2] for p in own[i])
            total, reserve = Counter(), Counter()
            for (a, _), n in left.items():
                total[a] += n
                reserve[a] += cuts[min(n, 3)]
            bits = 0.0
            for a, p, base in own[i]:
                n, low = left[a, p], 2.0**-base
                bits -= math.log2((max(n - cuts[min(n, 3)], 0) + reserve[a] * low) / total[a] if total[a] else low)
            size = len(byte_bits[i])
            out[i] = (lang, byte_bits[i].sum() / max(1, size), bits / max(1, size))
    return out


def brute_kept(rows, spread=3.0):
    scores, kept = brute_quality(rows), {}
    failed = {}
    for i, t, _ in rows:
        w = re.findall(r"[^\x20\x09-\x0D]+", t or "")
        tri = Counter(tuple(w[k : k + 3]) for k in range(len(w) - 2))
        rep = {x for k in range(len(w) - 2) if tri[tuple(w[k : k + 3])] > 1 for x in range(k, k + 3)}
        failed[i] = len(w) < 50 or 100 * len(rep) > 50 * len(w)
    for lang in {x for x, _, _ in scores.values()}:
        texts = {t or "": scores[i] for i, t, x in rows if (x or "") == lang and not failed[i]}
        edge = []
        for k in (1, 2):
            values = sorted(x[k] for x in texts.values())
            q = [values[max(0, math.ceil(p * len(values)) - 1)] for p in (0.25, 0.75)] if values else [0, 0]
            wide = spread * max(q[1] - q[0], quality.LEAST_SPREAD)
            edge.append((q[0] - wide, q[1] + wide))
        for i, t, x in rows:
            if (x or "") == lang:
                kept[i] = not failed[i] and (not texts or edge[0][0] <= scores[i][1] <= edge[0][1] and scores[i][2] <= edge[1][1])
    return kept


@pytest.mark.parametrize("part_bytes", [300, 4 << 20])
def test_quality_scores_and_verdicts(spark, part_bytes):
    rng = random.Random(10)
    lines = [words(8, rng) for _ in range(40)]
    rows = [(i, " ".join(rng.sample(lines, 20)), "en") for i in range(60)]
    mixed = rows[0][1].split()
    rng.shuffle(mixed)
    rows += [(100, " ".join(mixed), "en"), (101, None, "en"), (102, "", None), (103, " \n ", "en"), (104, "x" * 3000, "en"), (105, rows[3][1], "en"), (106, rows[3][1], "de")]
    rows += [(110 + i, " ".join(rng.sample(lines, 12)) + " ß" * i, None) for i in range(9)]
    rows += [(200, " ".join("".join(chr(rng.randrange(33, 126)) for _ in range(9)) for _ in range(120)), "en"), (201, words(20_000, rng), "en")]
    got = {r["doc_id"]: r for r in quality.judge(spark.createDataFrame(rows, "doc_id long, text string, lang string").repartition(3), part_bytes=part_bytes).collect()}
    want, kept = brute_quality(rows), brute_kept(rows)
    assert not got[100]["kept"] and not got[200]["kept"] and sum(got[i]["kept"] for i in range(60)) >= 57
    for i in want:
        assert got[i]["bits_per_char"] == pytest.approx(want[i][1], rel=1e-4)
        assert got[i]["piece_bits_per_char"] == pytest.approx(want[i][2], rel=1e-4)
    assert {i: r["kept"] for i, r in got.items()} == kept


def within_one(a, b):
    if abs(len(a) - len(b)) > 1:
        return False
    table = list(range(len(b) + 1))
    for i, x in enumerate(a, 1):
        last, table[0] = table[0], i
        for j, y in enumerate(b, 1):
            last, table[j] = table[j], min(table[j] + 1, table[j - 1] + 1, last + (x != y))
    return table[-1] <= 1


def test_levenshtein_automaton():
    rng = random.Random(6)
    lex = toxicity.Lexicon([b"idiot", b"moron", b"trash", b"ape"], [b"lowe"])
    auto = toxicity.Automaton(lex)
    found = [bytes(rng.choice(b"idotmrnash") for _ in range(rng.randrange(1, 8))) for _ in range(3000)]
    for w in lex.words:
        for i in range(len(w) + 1):
            found += [w[:i] + w[i + 1 :], w[:i] + b"x" + w[i:], w[:i] + b"x" + w[i + 1 :], w]
    found += [b"loweab", b"lowe", b"low"]
    buffer = b" ".join(found) + b" "
    data, begins, ends = toxicity._words(buffer)
    for w, k in zip(found, auto.match(data, begins, ends).tolist(), strict=True):
        exact = w in lex.words or w.startswith(b"lowe")
        fuzzy = any(within_one(w, t) for t in lex.words if len(t) >= 5)
        assert k == (toxicity.EXACT if exact else toxicity.FUZZY if fuzzy else toxicity.NONE), w


def brute_features(text, words_, stems, window=8):
    raw = text.lower().encode()
    found = [(m.start(), m.end()) for m in re.finditer(rb"[a-z'\x80-\xff](?:[a-z'\x80-\xff]|(?<=[a-z'\x80-\xff])[0-9*@$!#_+](?=[a-z'\x80-\xff]))*", raw)]
    marks = [m.start() for m in re.finditer(b'"|\xe2\x80\x9c|\xe2\x80\x9d|\xe2\x80\x9e|\xc2\xab|\xc2\xbb', raw)]
    kinds = []
    for a, b in found:
        w = raw[a:b]
        exact = w in words_ or any(w.startswith(s) for s in stems)
        kinds.append(2 if exact else 1 if any(len(t) >= 5 and within_one(w, t) for t in words_) else 0)
    hits = [k for k, kind in enumerate(kinds) if kind]
    out = [0.0] * 7
    counts, most, plain = [0] * 4, 0, 0
    for k in hits:
        low, high = max(0, k - window), min(len(found) - 1, k + window)
        quoted = any(found[low][0] - 3 <= m < found[k][0] for m in marks) and any(found[k][1] <= m < found[high][1] + 3 for m in marks)
        burst = sum(low <= x <= high for x in hits)
        counts[(0 if kinds[k] == 2 else 2) + quoted] += 1
        if not quoted:
            most, plain = max(most, burst), plain + 1
    out[:4] = [math.log1p(c) for c in counts]
    out[4] = math.log1p(most)
    out[5] = min(1, 20 * plain / max(1, len(found)))
    out[6] = float(counts[0] > 0)
    return out


@pytest.mark.parametrize("block", [2, 150])
def test_features_against_brute_force(block):
    rng = random.Random(15)
    lexicon = toxicity.Lexicon([b"idiot", b"moron", b"trash", b"ape", b"clown"], [b"lowe"])
    auto = toxicity.Automata(lexicon, block)
    pool = ["idiot", "id1ot", "st*pid", "moron!", "trahs", "ape", "apes", "lower", "clown", "cl*wn", '"', "“x”", "hello", "world", "b", "é", "idi0t", "mor on"]
    texts = [" ".join(rng.choice(pool) for _ in range(rng.randrange(0, 40))) for _ in range(120)] + ["", "*", "a*", "x" * 30_000]
    buffer, starts = b"", [0]
    for t in texts:
        buffer += t.lower().encode() + b"\n"
        starts.append(len(buffer))
    got = toxicity.features(buffer, np.array(starts), auto)
    for k, t in enumerate(texts):
        assert got[k].tolist() == pytest.approx(brute_features(t, lexicon.words, lexicon.stems)), t


def test_lexicon_has_no_limit(spark):
    terms = [f"bad{chr(97 + i // 26)}{chr(97 + i % 26)}xq" for i in range(200)]
    rows = [(20 * i + k, f"some plain words {t} and more") for i, t in enumerate(terms) for k in range(20)]
    rows += [(5000 + i, f"some plain words and more by{i // 4}") for i in range(4000)]
    labels = [(i, int(i < 5000)) for i, _ in rows] + [(0, 0), (5000, None)]
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    model = toxicity.learn(docs, spark.createDataFrame(labels, "doc_id long, toxic int"), F.lit(True))
    got = {r["doc_id"]: r["score"] for r in toxicity.score(docs, model).collect()}
    assert all((got[i] >= 0.7) == (i < 4000) for i, _ in rows)
    assert len(model.lexicon.words) == 200
    assert toxicity.score(docs.limit(0), model).count() == 0


def test_chance_is_the_binomial_tail():
    for n, k, p in ((7, 5, 0.3), (4, 4, 0.5), (9, 0, 0.2)):
        assert toxicity.chance(k, n - k, p) == pytest.approx(sum(math.comb(n, j) * p**j * (1 - p) ** (n - j) for j in range(k, n + 1)))


def test_quotation_counts_apart():
    auto = toxicity.Automaton(toxicity.Lexicon([b"idiot"], []))
    buffer = b'he said "you idiot" to me\nyou idiot\n'
    x = toxicity.features(buffer, np.array([0, 26, 36]), auto)
    assert x[0, 0] == 0 and x[0, 1] > 0 and x[1, 0] > 0 and x[1, 1] == 0


def test_toxicity_learns(spark):
    rng = random.Random(7)
    rows, labels = [], []
    for i in range(300):
        bad = i % 4 == 0
        t = words(60, rng) + (" you worthless clown " if bad else " fine ") + words(20, rng)
        rows.append((i, t))
        labels.append((i, int(bad)))
    docs = spark.createDataFrame(rows + [(900, None), (901, "")], "doc_id long, text string")
    model = toxicity.learn(docs, spark.createDataFrame(labels, "doc_id long, toxic int"), F.col("doc_id") < 200)
    got = {r["doc_id"]: r["score"] for r in toxicity.score(docs, model).collect()}
    assert all((got[i] >= 0.7) == (i % 4 == 0) for i in range(200, 300))
    assert got[900] < 0.5 and got[901] == got[900]
    none = toxicity.learn(docs, spark.createDataFrame([], "doc_id long, toxic int"), F.lit(True))
    assert {r["score"] for r in toxicity.score(docs, none).collect()} == {0.0}


def test_language(spark):
    rng = random.Random(8)
    parts = {"aa": ["ba", "be", "bo", "lu"], "bb": ["kri", "stü", "zwa", "xi"]}
    rows = [(i, " ".join("".join(rng.choice(parts[k]) for _ in range(3)) for _ in range(12)), k) for i, k in enumerate(["aa", "bb"] * 60)]
    rows += [(500, None, "aa"), (501, "123 !?", "aa"), (502, "", None), (503, "babe luba", None)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string")
    trees = language.learn(docs, F.col("doc_id") < 80)
    got = {r["doc_id"]: (r["lang_pred"], r["score"]) for r in language.identify(docs, trees).collect()}
    assert all(got[i][0] == k for i, _, k in rows[80:120])
    assert [got[i] for i in (500, 501, 502)] == [("und", 0.0)] * 3 and got[503][0] == "aa"
    assert all(0 <= s <= 1 for _, s in got.values())
    assert {r["lang_pred"] for r in language.identify(docs, {}).collect()} == {"und"}


def brute_bits(sample, text):
    """Code length of text after counting sample, byte by byte, longest context first."""
    seen = {}
    data = b"\n\n\n" + b"\n\n\n".join(sample) + b"\n\n\n"
    for i in range(len(data)):
        for k in range(4):
            if i >= k:
                seen.setdefault(data[i - k : i], Counter())[data[i]] += 1
    bits, data = 0.0, b"\n\n\n" + text + b"\n\n\n"
    for i in range(3, len(data)):
        for k in (3, 2, 1, 0):
            follow = seen.get(data[i - k : i])
            if follow is None:
                continue
            total = sum(follow.values()) + len(follow)
            if data[i] in follow:
                bits -= math.log2(follow[data[i]] / total)
                break
            bits -= math.log2(len(follow) / total)
        else:
            bits += 8
    return bits


def test_language_scores_are_code_lengths(spark):
    rng = random.Random(14)
    parts = {"aa": ["ba", "be", "bo", "lu"], "bb": ["kri", "stü", "zwa", "xi"], "cc": ["ba", "kri", "é"]}
    rows = [(i, " ".join("".join(rng.choice(parts[k]) for _ in range(2)) for _ in range(rng.randrange(1, 9))), k) for i, k in enumerate(["aa", "bb", "cc"] * 20)]
    rows += [(900, "lu" * 30_000, "dd"), (901, "lu" * 20_000 + "é", None), (902, "?!", "aa"), (3, rows[3][1], "aa")]
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string")
    trees = language.learn(docs, F.col("doc_id") % 2 == 0)
    assert sorted(trees) == ["aa", "bb", "cc", "dd"]  # a language of long texts only is learned too
    samples = {k: sorted({t.encode()[:20_000] for i, t, x in rows if x == k and i % 2 == 0}) for k in trees}
    got = {(r["doc_id"]): (r["lang_pred"], r["score"]) for r in language.identify(docs, trees).collect()}
    for i, t, _ in rows:
        if len(t) > 1000 or i == 902:
            continue
        bits = {k: brute_bits(samples[k], t.encode()) for k in samples}
        best = min(sorted(bits), key=lambda k: bits[k])
        assert got[i][0] == best
        assert got[i][1] == pytest.approx(1 / sum(2.0 ** (bits[best] - b) for b in bits.values()), rel=1e-3)
    assert got[902] == ("und", 0.0) and got[901][0] == "dd"


def test_context_tree_is_a_code():
    tree = language.ContextTree([b"abracadabra " * 5])
    for quad in (b"\n\n\n", b"bra", b"zzz"):
        base = int.from_bytes(quad, "big") << 8
        total = np.exp2(-tree.bits(np.arange(base, base + 256, dtype=np.uint32))).sum()
        assert 0.3 < total <= 1 + 1e-9  # without exclusion a code wastes, and never exceeds


@pytest.mark.parametrize(
    "run",
    [
        lambda d: packing.pack(d),
        lambda d: neardup.link(d),
        lambda d: sharding.shard(d),
        lambda d: decontam.find(d, d.sparkSession.createDataFrame(ITEMS, "item_id long, text string")),
        lambda d: suffix_tree.dedup(d),
        lambda d: suffix_array.dedup(d),
        lambda d: quality.judge(d),
        lambda d: language.identify(d, language.learn(d, F.lit(True))),
        lambda d: htmltext.render(d, "text", "plain"),
    ],
)
def test_empty_tables(empty, run):
    assert run(empty).count() == 0


def test_pipeline_stages(spark, docs):
    corpus_pipeline = pytest.importorskip("corpus_pipeline")
    import tempfile

    folder = tempfile.mkdtemp()
    spark.createDataFrame(ITEMS, "item_id long, text string").write.parquet(f"{folder}/benchmark.parquet")
    now = docs
    for name, stage in corpus_pipeline.STAGES:
        to = f"{folder}/{name}"
        stage(spark, now, folder).write.parquet(to)
        before, now = now, spark.read.parquet(to)
        if name != "pack":
            assert now.columns == docs.columns and now.count() <= before.count()
    assert {"doc_id", "sequence_id", "ids"} <= set(now.columns)
