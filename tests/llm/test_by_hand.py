"""Whole queries that SQL cannot express against slow, plain versions of their own: op4, op8's verdict, op9, op4 in the pipeline."""

import math
import re
import struct
import zlib
from collections import Counter, defaultdict

import numpy as np
import pytest
from pyspark.sql import functions as F

import corpus_pipeline
from replica_sync.llm import media_avi, quality_nb, quality_rules, queries

WORD = re.compile(rb"[^\x20\x09-\x0d]+")


@pytest.fixture(scope="module")
def texts(spark, sf):
    return {r["doc_id"]: r["text"] for r in spark.read.parquet(f"{sf}/documents.parquet").collect()}


# ---- 4 ----
def shaped(text):
    """Letters to A or a, digits to 9, other signs as they are; runs of one sign once, white space as it is."""
    signs = bytes(65 if 65 <= b <= 90 else 97 if 97 <= b <= 122 or b >= 128 else 57 if 48 <= b <= 57 else b for b in text)
    white = b" \t\n\x0b\x0c\r"
    return bytes(b for i, b in enumerate(signs) if i == 0 or b != signs[i - 1] or b in white)


def grams_by_hand(text):
    """Words, pairs, shapes, pairs of shapes, and which lengths of runs of one word begin in the text."""
    out = set()
    words = [w.lower() for w in WORD.findall(text)]
    shapes = WORD.findall(shaped(text))
    for kind, w in (("word", words), ("shape", shapes)):
        out |= {(kind, x) for x in w} | {(kind, *x) for x in zip(w, w[1:])}
    for more in (3, 5, 9):
        if any(len(set(words[i : i + more])) == 1 for i in range(len(words) - more + 1)):
            out.add(("run", more))
    return out


def test_features_are_distinct_grams(texts):
    """With so many bits that none meet, as many features as grams, and as many common ones between neighbours."""
    made = ["a a a", "a a a a a b b b", "A1b2 C3--d", "", "  ", "x y x y x", "9 99 999 9999 z", "no no no no no no no no no"]
    data = [t.encode() for t in [*made, *list(texts.values())[:60]]]
    doc, feature = quality_nb.features(data, 44)
    found = [set(feature[doc == i].tolist()) for i in range(len(data))]
    wanted = [grams_by_hand(t) for t in data]
    assert [len(x) for x in found] == [len(x) for x in wanted]
    assert [len(a & b) for a, b in zip(found, found[1:])] == [len(a & b) for a, b in zip(wanted, wanted[1:])]


def descent_by_hand(rows, sign, cost, rounds=12, seed=5):
    """One row's dual variable after the other, weights in a dictionary."""
    weight, dual = defaultdict(float), [0.0] * len(rows)
    order = np.random.default_rng(seed)
    for _ in range(rounds):
        largest = 0.0
        for i in order.permutation(len(rows)):
            margin = sum(weight[k] * x for k, x in rows[i].items())
            slope = sign[i] * margin - 1 + dual[i] / (2 * cost[i])
            bend = sum(x * x for x in rows[i].values()) + 1 / (2 * cost[i])
            step = max(dual[i] - slope / bend, 0.0) - dual[i]
            for k, x in rows[i].items():
                weight[k] += step * sign[i] * x
            dual[i] += step
            largest = max(largest, abs(step))
        if largest < 1e-4:
            break
    return weight


def scores_by_hand(texts, labels):
    """Ratios from counts in dictionaries, plain dual descent, and the logistic curve by bisected descent."""
    data = {i: (t or "").encode() for i, t in texts.items()}
    doc, feature = quality_nb.features(list(data.values()))
    has = {i: feature[doc == n].tolist() for n, i in enumerate(data)}
    size = 1 << quality_nb.BITS
    known = [i for i in texts if i in labels and zlib.crc32(str(i).encode()) % 3 != 1]
    seen = {c: Counter(f for i in known if labels[i] == c for f in has[i]) for c in (0, 1)}
    total = {c: sum(seen[c].values()) + size for c in (0, 1)}
    ratio = lambda f: math.log((seen[1][f] + 1) / total[1]) - math.log((seen[0][f] + 1) / total[0])

    def design(i):
        x = {f: ratio(f) for f in has[i]}
        norm = math.sqrt(sum(v * v for v in x.values())) or 1.0
        return {**{f: v / norm for f, v in x.items()}, "one": 1.0}

    import hashlib

    known.sort(key=lambda i: hashlib.md5(f"5#{i}".encode()).hexdigest())
    used, aside = [i for n, i in enumerate(known) if n % 4 != 3], [i for n, i in enumerate(known) if n % 4 == 3]
    share = Counter(labels[i] for i in used)
    weight = descent_by_hand([design(i) for i in used], [1 if labels[i] else -1 for i in used], [len(used) / (2 * max(share[labels[i]], 1)) for i in used])
    margin = lambda i: sum(weight[k] * x for k, x in design(i).items())
    good = sum(labels[i] for i in aside)
    aims = [(margin(i), (good + 1) / (good + 2) if labels[i] else 1 / (len(aside) - good + 2)) for i in aside]
    a, b = curve_by_hand(aims)
    return {i: 1 / (1 + math.exp(-(a * margin(i) + b))) for i in texts}


def curve_by_hand(aims):
    """Slope and offset at which both sums of errors vanish: the offset by bisection inside a bisection of the slope."""

    def error(a, b):
        return [1 / (1 + math.exp(-max(-50.0, min(50.0, a * m + b)))) - t for m, t in aims]

    def offset(a):
        low, high = -200.0, 200.0
        for _ in range(80):
            middle = (low + high) / 2
            low, high = (middle, high) if sum(error(a, middle)) < 0 else (low, middle)
        return low

    low, high = -50.0, 200.0
    for _ in range(60):
        middle = (low + high) / 2
        slope = sum(e * m for e, (m, _) in zip(error(middle, offset(middle)), aims)) + 1e-6 * middle
        low, high = (middle, high) if slope < 0 else (low, middle)
    return low, offset(low)


@pytest.fixture(scope="module")
def labels(spark, sf):
    return {r["doc_id"]: r["quality"] for r in spark.read.parquet(f"{sf}/labels.parquet").where(F.col("quality").isin(0, 1)).collect()}


@pytest.fixture(scope="module")
def scores(texts, labels):
    return scores_by_hand(texts, labels)


def test_scores(spark, sf, texts, scores):
    rows = queries.op4_quality_nb(spark, sf).collect()
    assert {r["doc_id"] for r in rows} == set(texts) and len(rows) == len(texts)
    assert all(abs(r["score"] - scores[r["doc_id"]]) < 1e-3 for r in rows)
    assert all(r["predicted"] == (scores[r["doc_id"]] >= 0.5) for r in rows if abs(scores[r["doc_id"]] - 0.5) > 1e-3)


def test_quality_stage(spark, sf, texts, scores):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    kept = {r["doc_id"]: r["text"] for r in corpus_pipeline.good_documents(spark, docs, sf).collect()}
    near = {i for i, s in scores.items() if abs(s - 0.5) <= 1e-3}
    assert set(kept) - near == {i for i, s in scores.items() if s >= 0.5} - near and all(texts[i] == t for i, t in kept.items())


def test_dual_descent_finds_the_least_loss():
    """The squared-hinge loss is convex: no step along any axis or random line makes the found weights' loss smaller."""
    r = np.random.default_rng(3)
    rows = [(np.arange(6), np.append(r.normal(size=5), 1.0)) for _ in range(60)]
    sign, cost = r.choice([-1.0, 1.0], 60), r.uniform(0.3, 2, 60)
    weight = quality_nb.dual_coordinate_descent(rows, sign, cost, 6, rounds=3000)
    x = np.array([v for _, v in rows])
    loss = lambda w: w @ w / 2 + (cost * np.maximum(1 - sign * (x @ w), 0) ** 2).sum()
    steps = [*np.eye(6), *r.normal(size=(40, 6))]
    assert all(loss(weight + e * s) >= loss(weight) for s in steps for e in (-1e-2, 1e-2))


# ---- 8 ----
def votes_by_hand(text):
    """(failed, votes): the seven rules said in plain Python."""
    words = [w.decode() for w in WORD.findall((text or "").encode())]
    windows = Counter(zip(words, words[1:], words[2:]))
    repeats = len({i + k for i in range(len(words) - 2) if windows[tuple(words[i : i + 3])] > 1 for k in range(3)})
    lines = [x for x in (text or "").split("\n") if WORD.search(x.encode())]
    n = max(len(words), 1)
    mean, symbols, again, copies = sum(map(len, words)) / n, len(re.findall(r"[#*$%&|<>]", text or "")) / n, repeats / n, (len(lines) - len(set(lines))) / max(len(lines), 1)
    bad = [len(words) < 20, mean < 2.5 or mean > 12, symbols > 0.2, again > 0.3, copies > 0.6, len(words) / max(len(lines), 1) < 3]
    prose = len(words) >= 50 and 3 <= mean <= 9 and symbols < 0.1 and again < 0.3 and copies < 0.6
    return len(words) < 50 or 100 * repeats > 50 * len(words), tuple([-int(x) for x in bad] + [int(prose)])


def posteriors_by_hand(votes):
    """Expectation and maximisation over rows, not patterns; the priors are those of the rules."""
    assumed = [rule.assumed() for rule in quality_rules.standard_rules()]
    worth = max(20.0, 0.05 * len(votes))
    share, chance = 0.8, assumed

    def chance_of_good(row):
        good, bad = share, 1 - share
        for k, v in enumerate(row):
            bad, good = bad * chance[k][v][0], good * chance[k][v][1]
        return good / (good + bad)

    for _ in range(50):
        weight = [chance_of_good(row) for row in votes]
        new = []
        for k, prior in enumerate(assumed):
            pair = []
            for c in (0, 1):
                sums = {v: worth * prior[v][c] + sum(p if c else 1 - p for row, p in zip(votes, weight) if row[k] == v) for v in (-1, 0, 1)}
                pair.append({v: x / sum(sums.values()) for v, x in sums.items()})
            new.append({v: (pair[0][v], pair[1][v]) for v in (-1, 0, 1)})
        before, share, chance = share, min(max(sum(weight) / len(votes), 1e-3), 1 - 1e-3), new
        if abs(share - before) < 1e-7:
            break
    return [chance_of_good(row) for row in votes]


def test_verdicts(spark, sf, texts):
    judged = {i: votes_by_hand(t) for i, t in texts.items()}
    chance = dict(zip(judged, posteriors_by_hand([v for _, v in judged.values()])))
    rows = quality_rules.judge_quality(spark.read.parquet(f"{sf}/documents.parquet")).collect()
    assert len(rows) == len(texts)
    for r in rows:
        failed, _ = judged[r["doc_id"]]
        assert math.isclose(r["posterior"], chance[r["doc_id"]], rel_tol=1e-6, abs_tol=1e-9)
        assert r["kept"] == (not failed and chance[r["doc_id"]] >= 0.5)


# ---- 9 ----
def chunks(data, at, end):
    """(name, kind of list or None, first byte, size) of the chunks between two places, lists gone into."""
    while at + 8 <= end:
        name, size = data[at : at + 4], struct.unpack_from("<I", data, at + 4)[0]
        if name in (b"RIFF", b"LIST"):
            yield name, data[at + 8 : at + 12], at + 12, size - 4
            yield from chunks(data, at + 12, at + 8 + size)
        else:
            yield name, None, at + 8, size
        at += 8 + size + size % 2


def jpeg_by_hand(data):
    """Samples of a lossless JPEG of one component, bit by bit, from its own tables and sizes."""
    assert data[:2] == b"\xff\xd8" and data[-2:] == b"\xff\xd9"
    at, codes = 2, {}
    while True:
        assert data[at] == 0xFF
        mark, size = data[at + 1], struct.unpack_from(">H", data, at + 2)[0]
        body = data[at + 4 : at + 2 + size]
        at += 2 + size
        if mark == 0xC4:
            code, place = 0, 17
            for length, many in enumerate(body[1:17], 1):
                for _ in range(many):
                    codes[length, code] = body[place]
                    code, place = code + 1, place + 1
                code <<= 1
        elif mark == 0xC3:
            depth, height, width = struct.unpack_from(">BHH", body)
        elif mark == 0xDA:
            predictor = body[3]
            break
    assert (depth, predictor) == (8, 1)
    coded = data[at:-2].replace(b"\xff\x00", b"\xff")
    bits = int.from_bytes(coded, "big")
    left = 8 * len(coded)

    def take(n):
        nonlocal left
        left -= n
        return bits >> left & ((1 << n) - 1)

    rows = []
    for y in range(height):
        rows.append([])
        for x in range(width):
            length, code = 1, take(1)
            while (length, code) not in codes:
                length, code = length + 1, code << 1 | take(1)
            k = codes[length, code]
            extra = take(k) if k else 0
            change = extra if k == 0 or extra >> (k - 1) else extra - (1 << k) + 1
            guess = rows[y][x - 1] if x else rows[y - 1][0] if y else 1 << (depth - 1)
            rows[y].append(guess + change)
    return bytes(v for row in rows for v in row)


def frames_by_hand(media):
    """Frames in the order of the index, which has to agree with the chunks of the movi list."""
    found = list(chunks(media, 0, len(media)))
    assert found[0][:2] == (b"RIFF", b"AVI ") and found[0][3] + 12 == len(media)
    movi = next(at for name, kind, at, _ in found if kind == b"movi")
    frames = [(at, size) for name, _, at, size in found if name == b"00dc"]
    at, size = next((at, size) for name, _, at, size in found if name == b"idx1")
    index = list(struct.iter_unpack("<4sIII", media[at : at + size]))
    assert [(movi - 4 + start + 8, n) for _, _, start, n in index] == frames and all(name == b"00dc" and flags == 16 for name, flags, _, _ in index)
    head = next(at for name, _, at, _ in found if name == b"avih")
    assert struct.unpack_from("<I", media, head + 16)[0] == len(frames)
    return [jpeg_by_hand(media[at : at + n]) for at, n in frames]


def shots_by_hand(frames):
    """Cuts where the histograms' change stands out of the changes around it, one frame at a time."""
    n = len(frames)
    if n < 3:
        return [(0, n)] if n else []
    bars = [Counter(v // 16 for v in f) for f in frames]
    change = [sum(abs(a[k] - b[k]) for k in range(16)) / (2 * 192) for a, b in zip(bars, bars[1:])]
    cuts = []
    for i, c in enumerate(change):
        around = [change[j] for j in range(max(0, i - 12), min(n - 1, i + 13)) if j != i]
        mean = sum(around) / len(around)
        spread = math.sqrt(sum((x - mean) ** 2 for x in around) / len(around))
        level = mean + 3 * spread + 0.02
        if abs(c - level) < 1e-7:
            return None  # too near to tell by other sums
        if c > level and c >= (change[i - 1] if i else 0.0) and c > (change[i + 1] if i + 1 < len(change) else 0.0):
            cuts.append(i + 1)
    return list(zip([0, *cuts], [*cuts, n]))


def test_media_by_another_decoder(spark, sf, texts):
    made = {-1: "a" * 192 * 20 + "Z" * 192 * 20, -2: "\x00\x7f" * 300, -3: "é漢\U0001f600" * 200}
    docs = spark.read.parquet(f"{sf}/documents.parquet").select("doc_id", "text").unionByName(spark.createDataFrame(list(made.items()), "doc_id bigint, text string"))
    known, told = {**texts, **made}, 0
    stored = media_avi.store_media(docs)
    media = {r["doc_id"]: bytes(r["media"]) for r in stored.collect()}
    clips = defaultdict(list)
    for r in media_avi.clip_rows(stored).orderBy("clip").collect():
        clips[r["doc_id"]].append((r["first_frame"], r["end_frame"], r["start_s"], r["end_s"]))
    for r in media_avi.media_digests(stored).collect():
        frames = frames_by_hand(media[r["doc_id"]])
        data = (known[r["doc_id"]] or "").encode()
        payload = b"".join(frames)
        assert payload == data + b" " * (len(payload) - len(data)) and len(payload) == max(192, -(-len(data) // 192) * 192)
        shots = shots_by_hand(frames)
        if shots is not None:
            told += 1
            assert r["feature"] == ",".join(f"{a / 25:.2f}-{b / 25:.2f}" for a, b in shots)
            assert clips[r["doc_id"]] == [(a, b, a / 25, b / 25) for a, b in shots]
    assert told > 0.9 * len(known)
