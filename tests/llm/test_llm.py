"""The training-data operators against plain Python, and their edge cases."""

import hashlib
import itertools
import math
import random
import re
import zlib
from collections import Counter

import numpy as np
import pytest
from pyspark.sql import functions as F

from replica_sync.llm import bpe, html_extract, jaccard_join, lm_score, media_avi, mixing, quality_nb, quality_rules, queries, secret_scan, token_files
from replica_sync.llm.blocks import counted, packed, unpacked
from replica_sync.llm.common import Words
from replica_sync.llm.graphs import components

SCHEMA = "doc_id bigint, text string, lang string, source string, n_chars bigint, block int, spans string, hash string"


@pytest.fixture(scope="module")
def odd(spark):
    """Nulls, empty and long texts, ties, repeated rows, extra columns with clashing names."""
    long = " ".join(f"w{i % 977}" for i in range(30_000))
    texts = [None, "", " \n\t ", "one", "One", "two words", "same text here for all", "same text here for all", long, "a" * 50_000, "password = hunter2hunter2 ok", "ünï cödé 漢字   wide"]
    rows = [(i, t, "en", None if i == 3 else f"s{i % 3}", len(t or ""), 1, "x", "y") for i, t in enumerate(texts)]
    rows += [rows[6], rows[6], (None, "no id", "en", "s1", 5, 1, "x", "y"), (99, None, None, None, None, None, None, None)]
    return spark.createDataFrame(rows, SCHEMA)


@pytest.fixture(scope="module")
def empty(spark):
    return spark.createDataFrame([], SCHEMA)


@pytest.fixture(scope="module")
def docs(spark, sf):
    return spark.read.parquet(f"{sf}/documents.parquet")


@pytest.fixture(scope="module")
def texts(docs):
    return {r["doc_id"]: r["text"] for r in docs.collect()}


OPERATORS = {
    "lm": lm_score.score_texts,
    "jaccard": jaccard_join.similar_documents,
    "bpe": bpe.encode_texts,
    "mixing": mixing.mix_sources,
    "token_files": token_files.token_files_round_trip,
    "rules": quality_rules.judge_quality,
    "media": lambda d: media_avi.media_digests(media_avi.store_media(d)),
    "secrets": secret_scan.scan_secrets,
}


@pytest.mark.parametrize("name", OPERATORS)
def test_odd_rows(odd, name):
    """One row for each row, whatever it holds."""
    rows = OPERATORS[name](odd).collect()
    assert len(rows) == odd.count()
    assert Counter(r["doc_id"] for r in rows) == Counter(r["doc_id"] for r in odd.select("doc_id").collect())


@pytest.mark.parametrize("name", OPERATORS)
def test_empty_table(empty, name):
    assert OPERATORS[name](empty).count() == 0


# ---- shared kernels ----
def test_words_are_those_of_bytes_split():
    r = random.Random(4)
    texts = ["".join(r.choice("aB \t\n\x0bé漢!\x1c") for _ in range(r.randint(0, 60))).encode() for _ in range(300)] + [b"", b"x" * 300_000 + b" y"]
    words = Words(texts)
    want = [(i, w) for i, t in enumerate(texts) for w in t.lower().split()]
    assert words.doc.tolist() == [i for i, _ in want]
    known = {}
    assert all(known.setdefault(w, h) == h for (_, w), h in zip(want, words.hash.tolist())) and len(set(known.values())) == len(known)


def test_packing_is_exact():
    r = random.Random(5)
    for keys in ([], [0], [2**64 - 1], [0, 2**64 - 1], sorted({r.getrandbits(64) for _ in range(500)}), list(range(300))):
        counts = [r.choice([0, 1, 254, 255, 256, 10**12]) for _ in keys]
        k, c = unpacked(packed(np.array(keys, dtype=np.uint64), np.array(counts, dtype=np.int64)))
        assert k.tolist() == keys and c.tolist() == counts
    keys, counts, place = counted(np.array([3, 1, 3], dtype=np.uint64), np.array([1.0, 0, 2]))
    assert keys.tolist() == [1, 3] and counts.tolist() == [0, 3] and place.tolist() == [1, 0, 1]


def test_components(spark):
    links = [("a", "b"), ("b", "c"), ("x", "y")] + [(f"n{i:03d}", f"n{i + 1:03d}") for i in range(60)]
    found = {r["node"]: r["root"] for r in components(spark.createDataFrame(links, "a string, b string")).collect()}
    assert found["c"] == "a" and found["y"] == "x" and {found[f"n{i:03d}"] for i in range(61)} == {"n000"}
    assert components(spark.createDataFrame([], "a string, b string")).count() == 0


# ---- 1 ----
@pytest.mark.parametrize(
    "page, text",
    [
        (None, ""),
        ("", ""),
        ("<html><body></body></html>", ""),
        ("<nav>Menu</nav><article><h1>Title</h1><p>First &amp; <b>second</b>,\n third.<p>Next<br>line.</article><footer>Foot</footer>", "Title\n\nFirst & second, third.\n\nNext line."),
        ("<body><div class='sidebar'>Other, long, text. With marks.</div><div><p>Body text, of it. More.</p><p>Short</p></div><div id=comments><p>I say, this. And that.</p></div></body>", "Body text, of it. More.\n\nShort"),
        ("<body><script>var x = '<p>no</p>';</script><p>Only this.</p><form>Mail <input></form>", "Only this."),
        ("<article><header><h1>Head</h1></header><p>Said: 1 &lt; 2.</p><aside>Ad</aside></article>", "Head\n\nSaid: 1 < 2."),
        ("plain words, no markup", "plain words, no markup"),
        ("<body><div class='ad'>Buy this now, please. It is good, cheap, new.</div><article><h1>Stub</h1></article>", "Stub"),
    ],
)
def test_pages(page, text):
    assert html_extract.extract(page) == text


SAID = "The council met on Monday, and voted for the plan. It will cost much, said the mayor; others agreed."
STORY = "".join(f"<p>{SAID} {SAID} Number {k}.</p>" for k in range(3))
TOLD = "\n\n".join(f"{SAID} {SAID} Number {k}." for k in range(3))


@pytest.mark.parametrize(
    "page, text",
    [
        (f"<body><nav>Menu</nav><div class='content share-enabled'>{STORY}</div></body>", TOLD),
        (f"<body><div id='search-results'>{STORY}</div></body>", TOLD),
        (f"<body><article><h1>Title</h1><p class='notice-date'>Published 3 May</p>{STORY}</article></body>", f"Title\n\nPublished 3 May\n\n{TOLD}"),
        (f"<body><div class='story'>{STORY}</div><div class='feedback'><p>I liked this, thanks. Great.</p></div></body>", TOLD),
        (f"<body><div class='story'>{STORY}</div><div class='feedback'><p>{SAID} {SAID}</p></div></body>", TOLD),
        (f"<body><div class='outbrain'><p>Buy one, get two.</p></div><div class='story'>{STORY}</div></body>", TOLD),
        (f"<body><div class='xyz'><p>Buy one, get two.</p></div><div class='story'>{STORY}</div></body>", TOLD),
        (f"<body><form action='/'><div id='sidebar'>{STORY}</div></form></body>", TOLD),
        (f"<body>{STORY}<ul><li><a href='/1'>One</a></li><li><a href='/2'>Two</a></li><li><a href='/3'>Three</a></li></ul></body>", TOLD),
        (f"<body><div class='story'>{STORY}<ul><li>a point</li><li>another</li></ul></div></body>", f"{TOLD}\n\na point\n\nanother"),
    ],
)
def test_ratios_decide_and_names_do_not(page, text):
    assert html_extract.extract(page) == text


def test_path_ratios_by_hand(spark, sf):
    """Ratio, smoothing and threshold, one block at a time."""
    sources = [f"<body><div class='story'><h1>Title</h1>{STORY}<p>Short.</p></div><div class='x'><p>Aside, really.</p></div></body>", *[r["html"] for r in spark.read.parquet(f"{sf}/pages.parquet").limit(8).collect()]]
    for source in sources:
        page = html_extract.Page(source)

        def section(node):
            while node and page.name[node] not in html_extract.SECTIONS:
                node = page.parent[node]
            return node

        rows = [(page.path[o], section(o), t) for o, t in page.blocks]
        fused = []
        for i, (_, home, _) in enumerate(rows):
            sums = [0.0, 0.0, 0.0]
            for j, (path, other, _) in enumerate(rows):
                if abs(i - j) <= 3 and other == home:
                    same = [t for p, _, t in rows if p == path]
                    weight = math.exp(-((i - j) ** 2) / 2)
                    sums[0] += weight
                    sums[1] += weight * sum(map(len, same)) / len(same)
                    sums[2] += weight * sum(len(html_extract.PUNCTUATION.findall(t)) for t in same) / len(same)
            fused.append(sums[1] / sums[0] * (1 + sums[2] / sums[0]))
        mean = sum(fused) / len(fused)
        cut = min(math.sqrt(sum((x - mean) ** 2 for x in fused) / len(fused)), max(fused) / 2)
        holder = np.array([h for _, h, _ in rows])
        every = list(range(len(rows)))
        assert np.allclose(html_extract.path_scores(page, every, holder), fused, rtol=1e-9)
        near = [abs(x - cut) < 1e-9 * cut for x in fused]
        assert [i in html_extract.content_blocks(page, every, holder, 1.0, 1.0) for i in every if not near[i]] == [x >= cut for i, x in enumerate(fused) if not near[i]]


def test_pages_of_the_tables(spark, sf):
    def article(source):
        inner = re.search(r"<article>(.*)</article>", source, re.S)[1]
        import html

        found = [" ".join(html.unescape(re.sub(r"<[^>]+>", " ", x)).split()) for x in re.split(r"</?(?:p|h1)>", inner)]
        return "\n\n".join(x for x in found if x)

    pages = {r["page_id"]: r["html"] for r in spark.read.parquet(f"{sf}/pages.parquet").collect()}
    rows = queries.op1_html_extraction(spark, sf).collect()
    assert len(rows) == len(pages) and all(r["text"] == article(pages[r["page_id"]]) and r["n_chars"] == len(r["text"]) for r in rows)


def test_deep_and_long_pages():
    assert html_extract.extract("<div>" * 20_000 + "Deep, text." + "</div>" * 20_000) == "Deep, text."
    assert len(html_extract.extract("<p>" + "word. " * 100_000)) == 599_999


def test_page_rows(spark):
    rows = spark.createDataFrame([(1, None, None, "x"), (1, "u", "<p>a</p>", "x"), (1, "u", "<p>a</p>", "x")], "page_id bigint, url string, html string, text string")
    assert sorted(r["text"] for r in html_extract.extract_pages(rows).collect()) == ["", "a", "a"]
    assert html_extract.extract_pages(rows.limit(0)).count() == 0


# ---- 2 ----
def lm_by_hand(texts, order=lm_score.ORDER, ladder=lm_score.LADDER):
    """Counts in dictionaries, one token at a time; the strengths by leaving each training token out in its turn."""
    tokens = {i: ["<", *(t or "").encode().lower().split(), ">"] for i, t in texts.items()}
    training = {i for i in tokens if zlib.crc32(str(i).encode()) % 10}
    count = Counter()
    for i in training:
        for at in range(len(tokens[i])):
            for m in range(1, order + 1):
                if at - m + 1 >= 0:
                    count[tuple(tokens[i][at - m + 1 : at + 1])] += 1
    real = {g[0]: n for g, n in count.items() if len(g) == 1 and g != ("<",)}
    total, kinds = sum(real.values()), len(real)

    def probability(words, at, strengths, less=0):
        p = (max(real.get(words[at], 0) - less, 0) + 0.1) / (total + 0.1 * (kinds + 1) - less)
        for m, k in enumerate(strengths, 2):
            if at - m + 1 >= 0:
                seen = count[tuple(words[at - m + 1 : at])] - less
                if seen > 0:
                    p = (max(count[tuple(words[at - m + 1 : at + 1])] - less, 0) + k * p) / (seen + k)
        return p

    def likelihood(strengths):
        return sum(math.log10(probability(tokens[i], at, strengths, 1)) for i in training for at in range(1, len(tokens[i])))

    best = max(itertools.product(ladder, repeat=order - 1), key=likelihood)
    out = {}
    for i, words in tokens.items():
        base = sum(math.log10((real.get(w, 0) + 0.1) / (total + 0.1 * (kinds + 1))) for w in words[1:])
        score = sum(math.log10(probability(words, at, best)) for at in range(1, len(words)))
        out[i] = (i not in training, len(words) - 1, sum(w in real for w in words[1:]), total, base, score)
    return out


@pytest.mark.parametrize("order, ladder", [(lm_score.ORDER, lm_score.LADDER), (2, (1.0, 50.0)), (4, (8.0,))])
def test_lm(docs, texts, order, ladder):
    want = lm_by_hand(texts, order, ladder)
    rows = lm_score.score_texts(docs, order=order, ladder=ladder).collect()
    assert len(rows) == len(want)
    for r in rows:
        held, n, known, total, base, score = want[r["doc_id"]]
        assert (r["held_out"], r["n_tokens"], r["n_known"], r["train_tokens"]) == (held, n, known, total)
        assert math.isclose(r["base_score"], base, rel_tol=1e-9) and math.isclose(r["score"], score, rel_tol=1e-9)


def test_lm_of_three_adds_up():
    """In every state the probabilities of all words and of one unseen word add up to 1."""
    texts = [b"a b a c", b"a b b a", b"c a b"]
    seq = lm_score.Sequences([*texts, *[b"a b " + w for w in (b"a", b"b", b"c", b"zzz")], b"a b"], 3)
    training = np.array([True] * 3 + [False] * 5)
    words, grams = lm_score.counts_of(seq, training)
    total, kinds = int(words[1].sum()), int((words[1] > 0).sum())
    automaton = lm_score.BackoffAutomaton(seq, words[2], words[1], grams[2], grams[1], total, kinds)
    taken, failed = automaton.traverse(seq)
    arc, fail = next(automaton.arcs((2.0,), (3.0,)))
    weights = 10 ** (arc[taken] + sum(fail[x] for x in failed))[seq.real]
    doc = seq.doc[seq.real]
    third = [weights[doc == 3 + k][2] for k in range(5)]
    assert math.isclose(sum(third), 1.0, rel_tol=1e-9)


def test_lanes_carry_their_state():
    """A long text read in lanes takes the same arcs as one read by a single lane."""
    r = np.random.default_rng(4)
    texts = [" ".join(r.choice(list("abcdefgh"), n)).encode() for n in (1, 63, 64, 65, 66, 400)]
    seq = lm_score.Sequences(texts, 3)
    words, grams = lm_score.counts_of(seq, np.array([True, True, False, True, False, False]))
    automaton = lm_score.BackoffAutomaton(seq, words[2], words[1], grams[2], grams[1], 200, 9)
    taken, failed = automaton.traverse(seq)
    lane, lm_score.LANE = lm_score.LANE, 1 << 20
    try:
        whole, whole_failed = automaton.traverse(seq)
    finally:
        lm_score.LANE = lane
    assert (taken == whole).all() and all((x == y).all() for x, y in zip(failed, whole_failed)) and failed[1].any()


# ---- 3 ----
def shingles(text, width=3):
    words = (text or "").encode().lower().split()
    return frozenset(tuple(words[i : i + width]) for i in range(max(1, len(words) - width + 1))) if words else frozenset()


def components_by_hand(texts):
    sets = {i: shingles(t) for i, t in texts.items()}
    root = {i: i for i in sets}

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    ids = sorted(sets)
    for n, i in enumerate(ids):
        for j in ids[:n]:
            a, b = sets[i], sets[j]
            if a and b and 100 * len(a & b) >= 90 * len(a | b):
                x, y = find(i), find(j)
                root[max(x, y)] = min(x, y)
    return {i: (len(sets[i]), find(i)) for i in ids}


def check_components(spark, texts):
    rows = jaccard_join.similar_documents(spark.createDataFrame(list(texts.items()), "doc_id bigint, text string")).collect()
    assert {r["doc_id"]: (r["n_shingles"], r["component_id"]) for r in rows} == components_by_hand(texts)


def test_join(spark, texts):
    check_components(spark, texts)


def test_join_of_families(spark):
    """Near copies of a few originals at similarities around the threshold, chains of them, and exact copies."""
    r = random.Random(9)
    words = [f"v{i}" for i in range(400)]
    texts = {}
    for family in range(4):
        base = [r.choice(words) for _ in range(90)]
        for _ in range(25):
            if r.random() < 0.3:
                base = list(base)
                base[r.randrange(90)] = r.choice(words)
            own = list(base)
            for _ in range(r.randint(0, 3)):
                own[r.randrange(90)] = r.choice(words)
            texts[len(texts)] = " ".join(own)
    for t in ("", "a", "a b", "A  b", "a b c", "a b c d", None, "b a"):
        texts[len(texts)] = t
    check_components(spark, texts)


def test_join_compares_few_pairs_of_a_large_group(spark, monkeypatch):
    """Copies of one text that differ a little too much to link: they meet under every order, but few pairs are made."""
    r = random.Random(4)
    base = [f"w{i}" for i in range(130)]
    texts = {}
    for i in range(120):
        own = list(base)
        for k in r.sample(range(5, 125), 2 if i % 8 else 1):
            own[k] = f"x{i}_{k}"
        texts[i] = " ".join(own)
    made, compared = [], jaccard_join.compared
    monkeypatch.setattr(jaccard_join, "compared", lambda pairs, *a: made.append(pairs.count()) or compared(pairs, *a))
    check_components(spark, texts)
    sets = [shingles(t) for t in texts.values()]
    links = sum(100 * len(a & b) >= 90 * len(a | b) for i, a in enumerate(sets) for b in sets[:i])
    assert links and sum(made) <= 3 * links, (made, links)


def test_sketches_refuse_no_link():
    r = np.random.default_rng(3)
    for n in (1, 5, 40, 130, 900, 5000):
        common = r.integers(0, 2**64, n, dtype=np.uint64)
        for own in (0, 1, n // 20, n // 10):
            a, b = (np.concatenate([common, r.integers(0, 2**64, own, dtype=np.uint64)]) for _ in range(2))
            doc = np.repeat([0, 1], [len(a), len(b)])
            x, y = jaccard_join.sketches(np.concatenate([a, b]), doc, 2)
            apart = int(np.bitwise_count(x ^ y).sum())
            assert apart <= 2 * own and (own > 13 or apart >= own)


def test_least_common():
    for n in range(1, 60):
        for m in range(1, 60):
            links = [o for o in range(min(n, m) + 1) if 100 * o >= 90 * (n + m - o)]
            if links:
                assert min(links) == -(-90 * (n + m) // 190) and n - min(links) <= jaccard_join.allowed_misses(np.array([n]))[0]


# ---- 4 ----
def test_quality(spark, sf):
    rows = queries.op4_quality_nb(spark, sf).collect()
    labels = {r["doc_id"]: r["quality"] for r in spark.read.parquet(f"{sf}/labels.parquet").collect()}
    held = [r for r in rows if r["held_out"] and r["doc_id"] in labels]
    assert all(0 <= r["score"] <= 1 and r["predicted"] == (r["score"] >= 0.5) for r in rows)
    assert sum(r["predicted"] == labels[r["doc_id"]] for r in held) / len(held) > 0.85
    assert all(r["held_out"] == (zlib.crc32(str(r["doc_id"]).encode()) % 3 == 1) for r in rows)


def test_held_out_labels_do_not_matter(spark, docs, sf):
    labels = spark.read.parquet(f"{sf}/labels.parquet")
    held = F.crc32(F.col("doc_id").cast("string").cast("binary")) % 3 == 1
    flipped = labels.withColumn("quality", F.when(held, 1 - F.col("quality")).otherwise(F.col("quality")))
    scores = lambda x: {r["doc_id"]: r["score"] for r in quality_nb.score_quality(docs, x).collect()}
    assert scores(labels) == scores(flipped)


def test_quality_edges(spark, odd, empty, docs, sf):
    labels = spark.read.parquet(f"{sf}/labels.parquet")
    assert quality_nb.score_quality(odd, labels).count() == odd.count()
    assert quality_nb.score_quality(empty, labels).count() == 0
    alike = quality_nb.score_quality(docs, labels.limit(0)).select("score").distinct().collect()
    assert len(alike) == 1


def test_dual_descent_separates():
    r = np.random.default_rng(1)
    rows = [(np.array([0, 1]), np.array([x, 1.0])) for x in np.concatenate([r.normal(2, 0.3, 40), r.normal(-2, 0.3, 40)])]
    sign = np.array([1.0] * 40 + [-1.0] * 40)
    w = quality_nb.dual_coordinate_descent(rows, sign, np.ones(80), 2)
    assert all(s * (w[at] @ x) > 0 for (at, x), s in zip(rows, sign))


# ---- 5 ----
def test_bpe(docs, texts):
    import tiktoken

    path, pattern = bpe.default_vocabulary()
    table = bpe.RankTable(path, pattern)
    library = tiktoken.Encoding("own", pat_str=pattern, mergeable_ranks=table.rank, special_tokens={})
    for r in bpe.encode_texts(docs).collect():
        ids = library.encode_ordinary(texts[r["doc_id"]])
        assert r["n_tokens"] == len(ids) and r["ids_sha256"] == hashlib.sha256(np.array(ids, dtype="<u4").tobytes()).hexdigest()
        assert r["decoded_sha256"] == hashlib.sha256(texts[r["doc_id"]].encode()).hexdigest()
    r = random.Random(6)
    for _ in range(500):
        text = "".join(r.choice("abeth ié\n\t$ß漢 1'\x1c\x85½²") for _ in range(r.randint(0, 50)))
        assert np.frombuffer(table.encode(text), dtype="<u4").tolist() == library.encode_ordinary(text)
    long = "ab" * 40_000
    assert np.frombuffer(table.encode(long), dtype="<u4").tolist() == library.encode_ordinary(long)


def test_bpe_round_trip(odd):
    again = bpe.decode_ids(bpe.encode_texts(odd, keep_ids=True)).collect()
    assert Counter((r["doc_id"], r["text"]) for r in again) == Counter((r["doc_id"], r["text"] or "") for r in odd.collect())


# ---- 6 ----
def filled(sizes, weights, most=3):
    """Water-filling by rounds: cap, share the excess by weight, until none is above."""
    total, capped = sum(sizes), set()
    while True:
        left = total - sum(most * sizes[i] for i in capped)
        weight = sum(weights[i] for i in range(len(sizes)) if i not in capped)
        target = [most * s if i in capped else left * weights[i] / weight for i, s in enumerate(sizes)]
        above = {i for i in range(len(sizes)) if i not in capped and target[i] > most * sizes[i]}
        if not above:
            return target
        capped |= above


def test_water_filling(spark):
    r = random.Random(8)
    for _ in range(4):
        sizes = [r.choice([1, 5, 40, 900, 5000]) for _ in range(r.randint(1, 9))]
        table = spark.createDataFrame([(f"s{i}", s, mixing.WEIGHTS[i % 3]) for i, s in enumerate(sizes)], "source string, source_size bigint, weight bigint")
        got = {x["source"]: x["target"] for x in mixing.water_filled(table).collect()}
        want = filled(sizes, [mixing.WEIGHTS[i % 3] for i in range(len(sizes))])
        assert all(math.isclose(got[f"s{i}"], t, rel_tol=1e-9) for i, t in enumerate(want))


def test_mixing(spark, docs, texts, sf):
    rows = queries.op6_mixing(spark, sf).collect()
    source = {r["doc_id"]: r["source"] for r in docs.collect()}
    taken, target = Counter(), {}
    for r in rows:
        assert r["size"] == len(re.findall(rb"[^\x20\x09-\x0d]+", texts[r["doc_id"]].encode())) and 0 <= r["taken"] <= 3 * r["size"]
        taken[source[r["doc_id"]]] += r["taken"]
        target[source[r["doc_id"]]] = r["target"]
    assert all(abs(taken[s] - t) <= 1 for s, t in target.items())
    names = sorted(target)
    sizes = [sum(r["size"] for r in rows if source[r["doc_id"]] == s) for s in names]
    want = filled(sizes, [mixing.WEIGHTS[i % 3] for i in range(len(names))])
    assert all(math.isclose(target[s], t, rel_tol=1e-9) for s, t in zip(names, want))
    again = queries.op6_mixing(spark, sf).collect()
    assert sorted(map(tuple, again)) == sorted(map(tuple, rows))


def test_whole_rows_are_taken_to_the_nearest(spark):
    """One long document a source: the last one is taken once more if at least half is due."""
    rows = [(i, s, " ".join(["w"] * 100)) for i, s in enumerate(("a", "b", "c"))] + [(9, "a", "")]
    docs = spark.createDataFrame(rows, "doc_id bigint, source string, text string")
    due = {r["doc_id"]: r["repeats"] for r in mixing.mix_sources(docs).collect()}
    taken = Counter(r["doc_id"] for r in mixing.repeated_rows(docs).collect())
    assert any(x % 1 >= 0.5 for x in due.values()) and due[9] == 0
    assert {i: taken[i] for i in due} == {i: math.floor(x + 0.5) for i, x in due.items()}


def test_mixing_is_native(spark, sf):
    plan = queries.op6_mixing(spark, sf)._jdf.queryExecution().toString() + queries.op8_quality_rules(spark, sf)._jdf.queryExecution().toString()
    assert not re.search("Python|Pandas|Arrow", plan)


# ---- 7 ----
def test_token_files(docs, texts):
    import public_tokenizers
    from tokenizers import Tokenizer

    library = Tokenizer.from_file(public_tokenizers.path("byte_bpe_50k.json"))
    rows = sorted(token_files.token_files_round_trip(docs, length=64, rows=4).collect(), key=lambda r: r["doc_id"])
    start = 0
    for r in rows:
        ids = [*library.encode(texts[r["doc_id"]], add_special_tokens=False).ids, 0]
        assert (r["start"], r["n_tokens"], r["ids_crc32"]) == (start, len(ids), zlib.crc32(np.array(ids, dtype="<u4").tobytes()))
        start += len(ids)


def test_added_tokens_are_those_of_the_library(spark):
    import public_tokenizers
    from tokenizers import Tokenizer

    library = Tokenizer.from_file(public_tokenizers.path("byte_bpe_50k.json"))
    assert library.encode("a <|endoftext|> b", add_special_tokens=False).ids == [64, 220, 50256, 275]
    texts = ["a <|endoftext|> b", "plain", "<|endoftext|><|endoftext|>\n\n x<|endoftext|>", "<|endoftext| >", "", "<|EndOfText|> a"]
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id bigint, text string").coalesce(1)
    start = 0
    for r in sorted(token_files.token_files_round_trip(docs, length=8, rows=2).collect(), key=lambda r: r["doc_id"]):
        ids = [*library.encode(texts[r["doc_id"]], add_special_tokens=False).ids, 0]
        assert (r["start"], r["n_tokens"], r["ids_crc32"]) == (start, len(ids), zlib.crc32(np.array(ids, dtype="<u4").tobytes()))
        start += len(ids)


def test_sequences(spark, tmp_path):
    docs = spark.createDataFrame([(1, "some words to be stored in a file"), (2, None)], "doc_id bigint, text string").coalesce(1)
    index = token_files.write_token_files(docs, f"file://{tmp_path}", length=8, rows=2).collect()
    assert {r["doc_id"]: r["n_tokens"] for r in index}[2] == 1
    reader = token_files.SequenceReader(f"file://{tmp_path}", index[0]["file"])
    ids, mask = reader.sequence(0)
    assert len(ids) == len(mask) == 8


# ---- 8 ----
def rules_by_hand(text):
    words = re.findall(r"[^\x20\x09-\x0d]+", text or "")
    windows = Counter(zip(words, words[1:], words[2:]))
    covered = {i + k for i in range(len(words) - 2) if windows[tuple(words[i : i + 3])] > 1 for k in range(3)}
    lines = [x for x in (text or "").split("\n") if re.search(r"[^\x20\x09-\x0d]", x)]
    return len(words), sum(map(len, words)), len(re.findall(r"[#*$%&|<>]", text or "")), len(lines) - len(set(lines)), len(covered)


def test_rules(spark, docs, odd, texts):
    strange = {0: "a b c a b c a b c", 1: "x\nx\n \n\nx y", 2: "a a a a", 3: "# <b> 50% & more", 4: None, 5: "one two three one two three four one two"}
    made = spark.createDataFrame(list(strange.items()), "doc_id bigint, text string")
    for frame, known in ((docs, texts), (made, strange)):
        for r in quality_rules.judge_quality(frame).collect():
            n, chars, symbols, copies, repeats = rules_by_hand(known[r["doc_id"]])
            assert (r["n_words"], r["word_chars"], r["n_symbols"], r["n_dup_lines"], r["n_repeat_words"]) == (n, chars, symbols, copies, repeats)
            failed = n < 50 or 100 * repeats > 50 * n
            assert r["base_failed"] == failed and not (failed and r["kept"])


def test_rules_tell_good_from_bad(spark, docs, sf):
    labels = {r["doc_id"]: r["quality"] for r in spark.read.parquet(f"{sf}/labels.parquet").collect()}
    rows = [r for r in quality_rules.judge_quality(docs).collect() if r["doc_id"] in labels]
    good = [r for r in rows if labels[r["doc_id"]] == 1 and not r["base_failed"]]
    bad = [r for r in rows if labels[r["doc_id"]] == 0]
    assert sum(r["kept"] for r in good) / len(good) > 0.95 and sum(r["kept"] for r in bad) / len(bad) < 0.4


def test_em_recovers_accuracies(spark):
    r = random.Random(3)
    counts = Counter()
    for _ in range(4000):
        good = r.random() < 0.7
        counts[tuple((1 if good else -1) * (1 if r.random() < q else -1) for q in (0.9, 0.8, 0.7))] += 1
    share, chance = quality_rules.fitted(list(counts.items()), [quality_rules.Rule("any", F.lit(True), F.lit(True), 0.85).assumed()] * 3)
    assert abs(share - 0.7) < 0.08 and chance[0][1][1] > chance[2][1][1] > 0.5


# ---- 9 ----
def test_media(docs, texts):
    for r in media_avi.media_digests(media_avi.store_media(docs)).collect():
        data = texts[r["doc_id"]].encode()
        payload = data + b" " * (max(192, -(-len(data) // 192) * 192) - len(data))
        media = media_avi.encode_avi(payload)
        assert (r["n_bytes"], r["payload_bytes"], r["media_bytes"]) == (len(data), len(payload), len(media))
        assert r["payload_sha256"] == hashlib.sha256(payload).hexdigest() and r["media_sha256"] == hashlib.sha256(media).hexdigest()
        assert r["tail_crc32"] == zlib.crc32(payload[-16:])


def test_media_is_lossless_for_any_bytes():
    r = random.Random(2)
    for n in (0, 1, 192, 193, 3000):
        payload = media_avi.payload_of(r.randbytes(n))
        media = media_avi.encode_avi(payload)
        assert media_avi.decode_frames(media).tobytes() == payload
        assert int.from_bytes(media[4:8], "little") == len(media) - 8
    edges = media_avi.payload_of(bytes([0, 255] * 200 + [255] * 200))
    assert media_avi.decode_frames(media_avi.encode_avi(edges)).tobytes() == edges


def test_index_and_chunks_agree():
    media = media_avi.encode_avi(media_avi.payload_of(bytes(range(256)) * 9))
    start, size = media_avi.riff_index(media)
    cut = media[: media.rindex(b"idx1")]
    other = media_avi.riff_index(cut)
    assert start.tolist() == other[0].tolist() and size.tolist() == other[1].tolist()
    with pytest.raises(ValueError):
        media_avi.riff_index(b"RIFF....WAVE")


def test_shots(spark):
    text = "a" * 192 * 20 + "Z" * 192 * 20
    rows = media_avi.clip_rows(media_avi.store_media(spark.createDataFrame([(1, text)], "doc_id bigint, text string"))).orderBy("clip").collect()
    assert [(r["first_frame"], r["end_frame"]) for r in rows] == [(0, 20), (20, 40)]


# ---- 10 ----
def secrets_by_hand(text):
    found = []
    for order, (pattern, flags, group, least) in enumerate([(r"(password|passwd|secret|token|api_?key)[\"']?\x20*[:=]\x20*[\"']?([A-Za-z0-9+/_.=-]+)", re.I | re.A, 2, 6), (r"AKIA[A-Z0-9]+", 0, 0, 20), (r"[0-9a-f]+", 0, 0, 24)]):
        found += [(m.start(), order, m.end()) for m in re.finditer(pattern, text or "", flags) if len(m.group(group)) >= least]
    return [(("assign", "access", "hex")[k], a, b) for a, k, b in sorted(found)]


def test_secrets(spark, docs, texts):
    made = {1: "Password: abcdef PASSWD='x1y2z3' token=short token = longer_one", 2: "AKIA" + "B" * 16 + " and AKIA123", 3: "f" * 24 + " " + "e" * 23 + "G" + "0" * 30, 4: None, 5: "ſecret=abcdefgh api_key: abcdefgh", 6: "漢 secret=abcdefgh"}
    for frame, known in ((docs, texts), (spark.createDataFrame(list(made.items()), "doc_id bigint, text string"), made)):
        for r in secret_scan.scan_secrets(frame).collect():
            want = secrets_by_hand(known[r["doc_id"]])
            assert [r["n_assign"], r["n_access"], r["n_hex"]] == [sum(k == x for k, _, _ in want) for x in ("assign", "access", "hex")]
            joined = [f"{k}:{a}:{b}" for k, a, b in want]
            assert r["base_sha256"] == hashlib.sha256(",".join(joined).encode()).hexdigest()
            assert [x for x in r["spans"].split(",") if x.split(":")[0] in ("assign", "access", "hex")] == joined


def test_long_url_logins_are_found():
    text = f"see https://{'u' * 70}:{'p' * 200}@host/path"
    assert secret_scan.spans(text) == [("url_login", 4, text.index("@") + 1)]


def test_ledger(spark, docs, tmp_path):
    """Two versions of a corpus and two rule versions: only unseen pairs are scanned, findings reach all rows."""
    path = f"file://{tmp_path}/ledger"
    ledger, other = secret_scan.BlobLedger(spark, path), secret_scan.BlobLedger(spark, path, "rules-2")
    held = lambda: sorted((r["rule_version"], n) for r, n in Counter(ledger.rows().select("rule_version").collect()).items())
    assert ledger.rows() is None
    distinct = docs.select("text").distinct().count()
    for _ in range(2):  # the second run adds nothing
        assert secret_scan.scan_secrets(docs, ledger=ledger).count() == docs.count() and held() == [("rules-1", distinct)]
    changed = docs.limit(3).unionByName(spark.createDataFrame([(10**6, "token = brandnewtoken", "en", "s", 1)], docs.schema))
    scanned = secret_scan.scan_unseen(changed, ledger.rows()).collect()
    assert [r["n_assign"] for r in scanned] == [1]
    found = {r["doc_id"]: r["n_assign"] for r in secret_scan.scan_secrets(changed, ledger=ledger).collect()}
    assert found[10**6] == 1 and len(found) == 4 and held() == [("rules-1", distinct + 1)]
    other.update(docs)
    assert held() == [("rules-1", distinct + 1), ("rules-2", distinct)]
    assert other.findings(docs).count() == docs.count()


def test_redaction_keeps_columns_of_any_name(spark):
    rows = spark.createDataFrame([(1, "password = hunter2hunter2", 3), (2, None, None)], "doc_id bigint, text string, `a.b` int")
    out = secret_scan.redact_secrets(rows)
    assert out.columns == rows.columns and sorted(tuple(r) for r in out.collect()) == [(1, "[secret]", 3), (2, None, None)]


def test_redaction(spark, odd):
    rows = {r["doc_id"]: r for r in secret_scan.redact_secrets(odd).collect()}
    assert rows[10]["text"] == "[secret] ok" and rows[10]["n_chars"] == len("[secret] ok") and rows[0]["text"] is None
    assert secret_scan.redact_secrets(odd).columns == odd.columns
