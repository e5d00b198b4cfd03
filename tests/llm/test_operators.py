"""Operators against brute force, on a given table and on odd rows."""

import collections
import hashlib
import itertools
import math
import random
import re
import zlib

import numpy as np
import pyarrow as pa
import pytest
import xxhash

from opframe.llm import common, cotrain, decontaminate, graph, learning, licences, lm, pieces, quality_rules, repair, sharding, simhash, toxicity

SCHEMA = "doc_id bigint, text string, lang string, source string, n_chars bigint, score double, shard int, fp string, key string, h bigint"
ODD = [
    (1, "Of the  idiot and trash, the\nend. Of the end!", "en", "s", 40),
    (1, "Of the  idiot and trash, the\nend. Of the end!", "en", "s", 40),
    (2, None, None, None, None),
    (3, "", "en", "s", 0),
    (None, "a null id has text too", "de", None, 5),
    (4, "x" * 70_000, "en", "s", 70_000),
    (5, "Ünïcode ñandú 日本語 🙂\t<|endoftext|> it's 12.5!", "es", "t", 9),
    (6, " \n\t ", "en", "s", 4),
    (7, "one two three four five six seven eight nine ten eleven twelve " * 400, "en", "s", 3),
    (8, "short", "en", "s", 5),
]


def odd(spark, rows=ODD):
    return spark.createDataFrame([(*r, 0.5, 3, "f", "k", 9) for r in rows], SCHEMA)


def empty(spark):
    return odd(spark, [])


def given(spark, sf, name="documents"):
    return spark.read.parquet(f"{sf}/{name}.parquet")


def lower(t):
    return "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in t or "")


def space_words(t):
    return re.findall(r"[^\x20\x09-\x0D]+", t or "")


# ---- 1 pieces --------------------------------------------------------------------------------


@pytest.fixture(scope="module")
def piece_model():
    import public_tokenizers

    return public_tokenizers.path("piece_bpe_32k.model")


def test_pieces_equal_the_library_and_decode(spark, sf, piece_model):
    import sentencepiece

    sp = sentencepiece.SentencePieceProcessor(model_file=piece_model)
    rows = [r.text for r in given(spark, sf).select("text").collect()] + [r[1] or "" for r in ODD]
    rows += ["a  b   c ", " lead", "aaaa aaaaaaa", "\n\n", "x\0y z", "".join(chr(c) for c in range(1, 600))]
    e = pieces.Encoder(piece_model)
    ids, n = e.encode(pa.array(rows))
    at = np.concatenate([[0], np.cumsum(n)])
    for i, want in enumerate(sp.encode(rows)):
        assert ids[at[i] : at[i + 1]].tolist() == want, rows[i][:60]
    assert e.decode(ids, n) == rows


def test_best_scoring_pieces_by_brute_force(piece_model):
    e = pieces.Encoder(piece_model)
    e.v.merges = False
    score = {t: e.v.score[i] for t, i in e.v.id_of.items()}
    for text in ("▁hello", "▁internat", "▁ab▁"):
        best = [0.0] + [-math.inf] * len(text)
        for j in range(1, len(text) + 1):
            best[j] = max(best[i] + score[text[i:j]] for i in range(j) if text[i:j] in score)
        ids, n = e._match([text])
        assert sum(e.v.score[ids]) == pytest.approx(best[-1]) and "".join(e.v.text[i] for i in ids) == text


def test_edges_are_all_occurrences(piece_model):
    e = pieces.Encoder(piece_model)
    text = "▁the▁there"
    code = np.array([e.v.code[ord(c)] for c in text] + [0], np.uint16)
    got = sorted(zip(*(x.tolist() for x in e.edges(code)), strict=True))
    want = sorted((m, m + len(t), i) for t, i in e.v.id_of.items() for m in range(len(text)) if text.startswith(t, m))
    assert got == want


def test_pieces_on_odd_rows(spark, piece_model):
    out = pieces.encode(odd(spark), piece_model).collect()
    assert len(out) == len(ODD) and all(r.round_trip for r in out) and {r.n_tokens for r in out if r.doc_id in (2, 3)} == {0}
    back = pieces.decode(pieces.encode(odd(spark), piece_model), piece_model).collect()
    assert collections.Counter(r.text for r in back) == collections.Counter(r[1] or "" for r in ODD)
    assert pieces.encode(empty(spark), piece_model).count() == 0


# ---- 2 decontamination -----------------------------------------------------------------------


def brute_scan(text, items, width=10):
    words = re.findall(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+", lower(text))
    hit, owners = set(), set()
    for item, t in items:
        w = re.findall(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+", lower(t))
        n = min(width, len(w))
        for i in range(len(w) - n + 1 if n else 0):
            for j in range(len(words) - n + 1):
                if words[j : j + n] == w[i : i + n]:
                    hit |= set(range(j, j + n))
                    owners.add(str(item))
    return len(words), len(hit), sorted(owners)


def test_scan_by_brute_force(spark):
    rng = random.Random(4)
    vocab = ["Alpha", "beta", "GAMMA", "ñu", "x1"]
    bench = [(i, " ".join(rng.choices(vocab, k=rng.choice([1, 2, 4, 5, 7])))) for i in range(9)] + [(20, "..!"), (21, None), (None, "beta beta beta beta")]
    docs = [(i, ", ".join(rng.choices(vocab, k=rng.randrange(30)))) for i in range(40)] + [(90, None), (91, ""), (91, "")]
    d = spark.createDataFrame(docs, "doc_id bigint, text string")
    b = spark.createDataFrame(bench, "item_id bigint, text string")
    items = [("" if i is None else i, t) for i, t in bench if t is not None]
    got = collections.Counter((r.doc_id, r.n_words, r.n_hit, tuple(r["items"])) for r in decontaminate.scan(d, b, 4).collect())
    assert got == collections.Counter((i, *brute_scan(t, items, 4)[:2], tuple(brute_scan(t, items, 4)[2])) for i, t in docs)
    clean = decontaminate.decontaminate(d, b, 4).collect()
    assert all(brute_scan(r.text, items, 4)[1] == 0 for r in clean)
    dropped = decontaminate.decontaminate(d, b, 4, "documents").collect()
    assert sorted(r.doc_id for r in dropped) == sorted(i for i, t in docs if not brute_scan(t, items, 4)[1])


def test_passes_unite(spark, sf, monkeypatch):
    docs, bench = given(spark, sf), given(spark, sf, "benchmark")
    cols = ["doc_id", "n_words", "n_hit", "items"]
    want = sorted(map(repr, decontaminate.scan(docs, bench).select(*cols).collect()))
    monkeypatch.setattr(decontaminate, "PASS_WORDS", 400)
    assert len(decontaminate._passes(bench, 10)) > 1
    assert sorted(map(repr, decontaminate.scan(docs, bench).select(*cols).collect())) == want


def test_passes_are_broadcast_one_at_a_time(spark, sf, monkeypatch):
    docs = given(spark, sf).select("doc_id", "text", "n_chars").unionByName(odd(spark).select("doc_id", "text", "n_chars"))
    bench = given(spark, sf, "benchmark")
    how = [lambda: decontaminate.scan(docs, bench), lambda: decontaminate.decontaminate(docs, bench, 10, "spans"), lambda: decontaminate.decontaminate(docs, bench, 10, "documents")]
    want = [sorted(map(repr, f().collect())) for f in how]
    sent, real = [], spark.sparkContext.broadcast
    monkeypatch.setattr(spark.sparkContext, "broadcast", lambda x: (sent.append(x), real(x))[1])
    monkeypatch.setattr(decontaminate, "PASS_WORDS", 700)
    n = len(decontaminate._passes(bench, 10))
    assert n > 1 and [sorted(map(repr, f().collect())) for f in how] == want
    assert len(sent) >= 3 * n and all(len(x) == 1 for x in sent)


def test_decontaminate_odd_rows(spark):
    bench = spark.createDataFrame([(1, "one two three four five six seven eight nine ten")], "item_id bigint, text string")
    out = {r.doc_id: r for r in decontaminate.decontaminate(odd(spark), bench).collect()}
    assert out[8].text == "short" and "one two" not in out[7].text and out[7].n_chars == len(out[7].text) and out[2].text is None
    assert decontaminate.decontaminate(odd(spark), bench).columns == odd(spark).columns
    assert decontaminate.scan(empty(spark), bench).count() == 0
    assert decontaminate.scan(odd(spark), bench.limit(0)).where("n_hit > 0").count() == 0


# ---- 3 SimHash -------------------------------------------------------------------------------


def brute_fingerprint(text, width=4):
    w = space_words(lower(text))
    sh = [" ".join(w[i : i + width]) for i in range(max(1, len(w) - width + 1))] if w else []
    h = [xxhash.xxh64_intdigest(s.encode(), 42) for s in sh]
    return sum(1 << k for k in range(64) if 2 * sum(x >> k & 1 for x in h) > len(h)) if h else 0


def brute_components(ids, fps, d=4):
    root = list(range(len(ids)))

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    for a, b in itertools.combinations(range(len(ids)), 2):
        if (fps[a] ^ fps[b]).bit_count() <= d:
            root[max(find(a), find(b))] = min(find(a), find(b))
    least = {}
    for i in range(len(ids)):
        least[find(i)] = min(least.get(find(i), ids[i]), ids[i])
    return {ids[i]: least[find(i)] for i in range(len(ids))}


@pytest.mark.parametrize("chunk", [2048, 3])
def test_simhash_by_brute_force(spark, sf, monkeypatch, chunk):
    monkeypatch.setattr(simhash, "CHUNK", chunk)
    rows = given(spark, sf).select("doc_id", "text").collect()
    near = [(1000 + i, r.text + " tail") for i, r in enumerate(rows[:40])] + [(2000 + i, rows[0].text.replace(" ", " q ", i)) for i in range(30)]
    docs = spark.createDataFrame([(r.doc_id, r.text) for r in rows] + near, "doc_id bigint, text string")
    texts = docs.collect()
    fps = [brute_fingerprint(r.text) for r in texts]
    got = {r.doc_id: (r.fp & (2**64 - 1), r.component_id) for r in simhash.near_duplicates(docs).collect()}
    want = brute_components([r.doc_id for r in texts], fps)
    assert got == {r.doc_id: (f, want[r.doc_id]) for r, f in zip(texts, fps, strict=True)}


def test_blocks_find_every_close_pair(spark):
    rng = random.Random(1)
    base = [rng.getrandbits(64) for _ in range(30)]
    fps = base + [b ^ sum(1 << k for k in rng.sample(range(64), 4)) for b in base]
    rows = [(x - (1 << 64) if x >> 63 else x,) for x in fps]
    nodes = spark.createDataFrame(rows, "fp bigint")
    for n in (10, 10**7, 10**9):
        linked = simhash.links(simhash.pigeonhole_keys(nodes, n, 4), 4).collect()
        near = {frozenset((a, b)) for (a,), (b,) in itertools.combinations(rows, 2) if ((a ^ b) & (2**64 - 1)).bit_count() <= 4}
        assert len(near) >= 30 and {frozenset((r.u, r.v)) for r in linked} <= near and len(linked) >= 30


def test_components_of_a_long_path(spark):
    e = spark.createDataFrame([(i, i + 1) for i in range(200)] + [(500, 501), (501, 500), (7, 7)], "u bigint, v bigint")
    assert {r.id: r.root for r in graph.components(e).collect()} == {**dict.fromkeys(range(201), 0), 500: 500, 501: 500}


def test_similar_texts_keep_one(spark):
    rng = random.Random(3)
    text = [" ".join(rng.choices([f"w{i}" for i in range(4000)], k=300)) for _ in range(30)]

    def change(t, n):
        w = t.split()
        for i in rng.sample(range(len(w)), n):
            w[i] = f"z{rng.random()}"
        return " ".join(w)

    rows = [(i, t) for i, t in enumerate(text)] + [(100 + i, change(t, 2)) for i, t in enumerate(text)] + [(200 + i, t) for i, t in enumerate(text)]
    docs = spark.createDataFrame(rows, "doc_id bigint, text string")
    kept = simhash.keep_one(docs, width=5, words64=4, max_diff=None)
    assert sorted(r.doc_id for r in kept.collect()) == list(range(30))


def test_simhash_odd_rows(spark):
    out = simhash.near_duplicates(odd(spark)).collect()
    assert len(out) == len(ODD)
    blank = [r for r in out if r.doc_id in (2, 3, 6)]
    assert {r.fp for r in blank} == {0} and {r.component_id for r in blank} == {2}
    kept = simhash.keep_one(odd(spark))
    assert kept.columns == odd(spark).columns
    ids = [r.doc_id for r in kept.collect()]
    assert ids.count(1) == 1 and 3 not in ids and 6 not in ids and None in ids
    assert simhash.near_duplicates(empty(spark)).count() == simhash.keep_one(empty(spark)).count() == 0


def test_keep_one_decides_by_row(spark):
    rng = random.Random(5)
    a, b, c, d, e = (" ".join(rng.choices([f"w{i}" for i in range(4000)], k=60)) for _ in range(5))
    rows = [(5, a), (7, a), (7, b), (None, a), (None, c), (None, d), (None, d), (8, e), (8, e), (9, e)]
    docs = spark.createDataFrame(rows, "doc_id bigint, text string")
    for how in ({}, {"width": 5, "words64": 4, "max_diff": None}):
        kept = collections.Counter((r.doc_id, r.text) for r in simhash.keep_one(docs, **how).collect())
        assert kept == collections.Counter([(5, a), (7, b), (None, c), (None, d), (8, e)])


def test_similar_means_jaccard_of_whole_sets(spark):
    rng = random.Random(11)

    def change(t, n):
        w = t.split()
        for i in range(0, 300, 300 // n):
            w[i] = f"z{rng.random()}"
        return " ".join(w)

    def sets(t):
        w = t.split()
        return {tuple(w[i : i + 5]) for i in range(len(w) - 4)}

    base = [" ".join(rng.choices([f"w{i}" for i in range(4000)], k=300)) for _ in range(60)]
    # about 0.85, 0.7 and 0.6 of the shingles in common; chains of texts whose ends are far apart
    rows = [(i, t) for i, t in enumerate(base)] + [(100 * k + i, change(t, n)) for k, n in ((1, 5), (2, 10), (3, 15)) for i, t in enumerate(base)]
    rows += [(1000 + i, base[0].rsplit(" ", 25 * i)[0]) for i in range(1, 6)] + [(2000, "a a a a a a a a a a b"), (2001, "a a a a a a a a a a c")]
    of = {i: sets(t) for i, t in rows}
    root = {i: i for i in of}

    def find(x):
        return x if root[x] == x else find(root[x])

    for a, b in itertools.combinations(sorted(of), 2):
        if len(of[a] & of[b]) >= 0.8 * len(of[a] | of[b]):
            a, b = find(a), find(b)
            root[max(a, b)] = min(a, b)
    docs = spark.createDataFrame(rows, "doc_id bigint, text string")
    got = {r.doc_id: r.component_id for r in simhash.near_duplicates(docs, width=5, words64=4, max_diff=None).collect()}
    assert got == {i: find(i) for i in of} and len(set(got.values())) > 150


# ---- 4 quality rules -------------------------------------------------------------------------


def brute_statistics(t):
    t = t or ""
    w = space_words(t)
    windows = collections.Counter(tuple(w[i : i + 8]) for i in range(len(w) - 7))
    covered = set()
    for i in range(len(w) - 7):
        if windows[tuple(w[i : i + 8])] > 1:
            covered |= set(range(i, i + 8))
    lines = [x for x in t.split("\n") if space_words(x)]
    return len(w), sum(map(len, w)), len(re.findall(r"[#*$%&|<>]", t)), len(lines) - len(set(lines)), len(covered)


def test_statistics_by_brute_force(spark, sf):
    rng = random.Random(2)
    extra = [(10_000 + i, rng.choice([" ", "\n", "\t"]).join(rng.choices(["a", "b#", "c|d", "ñ", "\x1f"], k=rng.randrange(60))), "en", "s", 1) for i in range(150)]
    docs = given(spark, sf).select("doc_id", "text", "lang", "source", "n_chars").unionByName(odd(spark, ODD + extra).select("doc_id", "text", "lang", "source", "n_chars"))
    cols = ["n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words"]
    got = collections.Counter((r.doc_id, *(r[c] for c in cols)) for r in quality_rules.statistics(docs).select("doc_id", *cols).collect())
    assert got == collections.Counter((r.doc_id, *brute_statistics(r.text)) for r in docs.collect())


def test_outliers_go_and_clean_texts_stay(spark, sf):
    sf = sf.replace("0.001", "0.01")
    out = quality_rules.judge(given(spark, sf)).join(given(spark, sf, "labels"), "doc_id").collect()
    clean = [r for r in out if r.quality == 1 and not r.base_failed]
    junk = [r for r in out if r.quality == 0]
    assert sum(r.kept for r in clean) >= 0.98 * len(clean) and sum(r.kept for r in junk) <= 0.5 * len(junk)
    assert not any(r.kept for r in out if r.base_failed)


def test_quality_rules_odd_rows(spark):
    out = {r.doc_id: r for r in quality_rules.judge(odd(spark)).collect()}
    assert out[2].base_failed and out[3].n_words == 0 and out[7].base_failed and {r.level for r in out.values()} == {0}
    assert quality_rules.judge(empty(spark)).count() == 0


def test_mcd_ignores_a_contaminated_quarter(spark):
    rng = np.random.default_rng(0)
    f = list(quality_rules.FEATURES)
    good, bad = rng.normal(0, 1, (900, len(f))), rng.normal(30, 1, (250, len(f)))
    rows = [("en", "s", *map(float, x)) for x in np.vstack([good, bad])]
    stats = spark.createDataFrame(rows, "lang string, source string, " + ", ".join(f"{c} double" for c in f))
    best = {tuple(r.g): r for r in quality_rules.estimates(stats).collect()}
    assert set(best) == {("en", "s"), ("en",), ()} and all(np.abs(r.mu).max() < 1 for r in best.values())


# ---- 5 language model ------------------------------------------------------------------------


def test_base_score_by_brute_force_and_mixture_is_better(spark, sf):
    from pyspark.sql import functions as F

    docs = given(spark, sf).select("doc_id", "text").unionByName(odd(spark).select("doc_id", "text"))
    out = lm.score(docs, common.doc_bucket("doc_id", 5) != 1).collect()
    rows = docs.collect()
    held = {r.doc_id for r in rows if zlib.crc32(("" if r.doc_id is None else str(r.doc_id)).encode()) % 5 == 1}
    tokens = [(r.doc_id, [*space_words(lower(r.text)), "\0end"]) for r in rows]
    c = collections.Counter(w for i, t in tokens if i not in held for w in t)
    total, types = sum(c.values()), len(c)
    want = collections.Counter((i, len(t), sum(c[w] > 0 for w in t), round(sum(math.log10((c[w] + 0.5) / (total + 0.5 * (types + 1))) for w in t), 6)) for i, t in tokens)
    assert collections.Counter((r.doc_id, r.n_tokens, r.n_known, round(r.base_score, 6)) for r in out) == want
    assert {r.train_tokens for r in out} == {total} and all(r.learnt == (r.doc_id not in held) for r in out)
    unseen = [r for r in out if not r.learnt]
    assert sum(r.score for r in unseen) > sum(r.base_score for r in unseen)
    assert docs.where(F.lit(False)).count() == lm.score(empty(spark), F.lit(True)).count() == 0


def brute_mixture(texts, order=3):
    """Deleted interpolation by dictionaries of strings: (score of every text, weights, log likelihoods of the steps, p(word | context))."""

    def counted(rows):
        grams = collections.Counter()
        for t in rows:
            padded = ["\0start"] * (order - 1) + t
            for i in range(order - 1, len(padded)):
                for n in range(1, order + 1):
                    grams[tuple(padded[i - n + 1 : i + 1])] += 1
        return grams, sum(map(len, rows)), len({w for t in rows for w in t}), len(rows)

    def context(grams, total, texts, gram):
        if len(gram) == 1:
            return total
        if gram[-2] == "\0start":
            return texts
        return grams[gram[:-1]]

    def parts(c, t):
        grams, total, _, texts = c
        padded = ["\0start"] * (order - 1) + t
        for i in range(order - 1, len(padded)):
            row = []
            for n in range(1, order + 1):
                gram = tuple(padded[i - n + 1 : i + 1])
                seen = context(grams, total, texts, gram)
                row.append((grams[gram] / seen if seen else 0.0, (min(1, seen) if n == 1 else min(lm.BUCKETS - 1, math.ceil(math.log2(seen + 1))))))
            yield row

    def mixture(row, types, w):
        p = 1 / (types + 1)
        for n, (f, b) in enumerate(row):
            p = w[n][b] * f + (1 - w[n][b]) * p
        return p

    estimating, held, every = ([t for t, role in texts if role in roles] for roles in ((lm.ESTIMATE,), (lm.HELD,), (lm.ESTIMATE, lm.HELD)))
    small, full = counted(estimating), counted(every)
    w = [[0.0] + [0.5] * (lm.BUCKETS - 1) for _ in range(order)]
    rows, likes = [r for t in held for r in parts(small, t)], []
    for _ in range(lm.EM_STEPS if rows else 0):
        used, offered, like = [[0.0] * lm.BUCKETS for _ in range(order)], [[0.0] * lm.BUCKETS for _ in range(order)], 0.0
        for r in rows:
            p, left = mixture(r, small[2], w), 1.0
            like += math.log(p)
            for n in reversed(range(order)):
                f, b = r[n]
                s = left * w[n][b] * f / p
                offered[n][b] += left * mixture(r[: n + 1], small[2], w) / p
                used[n][b] += s
                left *= 1 - w[n][b]
        for n in range(order):
            last = 0.5
            for b in range(1, lm.BUCKETS):
                if offered[n][b] > 0:
                    last = min(1 - 1e-6, max(1e-6, used[n][b] / offered[n][b]))
                w[n][b] = last
        if likes and like - likes[-1] <= lm.EM_GAIN * abs(like):
            break
        likes.append(like)
    scores = [sum(math.log10(mixture(r, full[2], w)) for r in parts(full, t)) for t, _ in texts]
    words = {x for t in every for x in t}
    given = lambda before: {x: mixture(list(parts(full, [*before, x]))[-1], full[2], w) for x in [*words, "\0unknown"]}
    return scores, w, likes, given


@pytest.mark.parametrize("keys", [lm.SLICE_KEYS, 500])
def test_mixture_by_brute_force(spark, sf, monkeypatch, keys):
    """Every n-gram counts, whatever the number of slices; the likelihood of left-out texts rises; probabilities add up to one."""
    from pyspark.sql import functions as F

    monkeypatch.setattr(lm, "SLICE_KEYS", keys)
    monkeypatch.setattr(lm, "CHUNK_BYTES", 40_000)
    docs = given(spark, sf).where("n_chars < 3000").select("doc_id", "text")
    left_out = F.pmod(F.xxhash64(F.col("doc_id").cast("string"), F.lit(5)), F.lit(lm.DELETED)) == 0
    test = common.doc_bucket("doc_id", 5) == 1
    rows = docs.select("doc_id", "text", F.when(test, lm.TEST).when(left_out, lm.HELD).otherwise(lm.ESTIMATE).alias("role")).collect()
    texts = [([*space_words(lower(r.text)), "\0end"], r.role) for r in rows]
    want, _, likes, after = brute_mixture(texts)
    assert likes == sorted(likes) and len(likes) > 3
    for before in ([], texts[0][0][:1], texts[0][0][:5], ["never", "seen"]):
        assert abs(sum(after(before).values()) - 1) < 1e-9
    got = {r.doc_id: r.score for r in lm.score(docs, ~test).collect()}
    assert all(abs(got[r.doc_id] - x) < 1e-6 * max(1, abs(x)) for r, x in zip(rows, want, strict=True))


def test_score_is_a_probability(spark):
    from pyspark.sql import functions as F

    docs = spark.createDataFrame([(1, "a b a b c"), (2, "b a"), (3, "a"), (4, "b"), (5, "c"), (6, "zzz")], "doc_id bigint, text string")
    out = {r.doc_id: r for r in lm.score(docs, F.col("doc_id") <= 2).collect()}
    # the first token is one of four known ones or unknown, each followed by an end; what is left of the mass is longer texts
    assert 0 < sum(10 ** out[i].score for i in (3, 4, 5, 6)) < 1


def test_no_training_text(spark):
    from pyspark.sql import functions as F

    out = lm.score(odd(spark), F.lit(False)).collect()
    assert all(r.base_score == 0 and r.n_known == 0 for r in out)


# ---- 6 and 9 classifiers ---------------------------------------------------------------------


def test_pu_risk_separates_without_negatives():
    rng = np.random.default_rng(0)
    pos, neg = rng.normal(1.5, 1, (800, 5)), rng.normal(-1.5, 1, (800, 5))
    u = np.vstack([rng.normal(1.5, 1, (300, 5)), rng.normal(-1.5, 1, (700, 5))])
    w = toxicity.nnpu(pos[:400], u, 0.3)
    f = lambda x: x @ w[:-1] + w[-1] > 0
    assert f(pos[400:]).mean() > 0.95 and f(neg).mean() < 0.05


def test_toxicity_on_held_out_rows(spark, sf):
    sf = sf.replace("0.001", "0.1")
    out = toxicity.query(spark, sf).join(given(spark, sf, "labels"), "doc_id").where("held_out").collect()
    rank = np.argsort(np.argsort([r.score for r in out]))
    y = np.array([r.toxic for r in out])
    auc = (rank[y == 1].sum() - y.sum() * (y.sum() - 1) / 2) / (y.sum() * (len(y) - y.sum()))
    assert auc > 0.93


def test_quality_on_held_out_rows(spark, sf):
    sf = sf.replace("0.001", "0.01")
    out = cotrain.query(spark, sf).join(given(spark, sf, "labels"), "doc_id").where("held_out").collect()
    assert np.mean([r.predicted == r.quality for r in out]) > 0.93


def test_classifiers_on_odd_rows(spark):
    none = spark.createDataFrame([], "doc_id bigint, quality int, toxic int")
    one = spark.createDataFrame([(1, 1, 1), (None, 0, 0), (8, 1, None)], "doc_id bigint, quality int, toxic int")
    for labels in (none, one):
        out = toxicity.score(odd(spark), toxicity.train(odd(spark), labels)).collect()
        assert len(out) == len(ODD) and all(0 <= r.score <= 1 for r in out) and out[0].shard == 3
        assert cotrain.score(odd(spark), cotrain.train(odd(spark), labels)).count() == len(ODD)
    two = spark.createDataFrame([(1, 0, 1), (7, 1, 0), (5, 1, 0), (4, 0, 0)], "doc_id bigint, quality int, toxic int")
    scored = cotrain.score(odd(spark), cotrain.train(odd(spark), two))
    assert scored.count() == len(ODD) and set(odd(spark).columns) <= set(scored.columns)
    m = toxicity.train(odd(spark), two)
    assert toxicity.score(empty(spark), m).count() == cotrain.score(empty(spark), cotrain.train(odd(spark), two)).count() == 0


def test_hash_sample_is_bounded(spark):
    rows = spark.range(5000).withColumnRenamed("id", "doc_id")
    assert learning.drawn(rows, 10_000, 1).count() == 5000 and 300 < learning.drawn(rows, 500, 1).count() < 700
    for bound, n in ((400, 10**11), (3000, 10**13), (4000, 4001)):
        assert abs((learning.share(bound, n) + 2**63) / 2**64 * n - bound) < 0.01 * bound
    texts = rows.selectExpr("doc_id", "repeat('x', 1000) as text")
    some = learning.drawn(texts, 500, 1, 100_000)
    assert 90 <= some.count() <= 101 and some.join(learning.drawn(texts, 500, 1), "doc_id", "left_anti").count() == 0
    assert learning.drawn(texts, 500, 1, 10).count() == 1


def test_models_do_not_depend_on_the_layout(spark):
    sf = "/root/testdata/sf0.01"
    docs, labels = given(spark, sf), given(spark, sf, "labels")
    dealt = docs.repartition(13, "source").sortWithinPartitions("n_chars")
    for train, score, columns in ((cotrain.train, cotrain.score, ("text_score", "meta_score", "score")), (toxicity.train, toxicity.score, ("score",))):
        a, b = ({r.doc_id: tuple(r[c] for c in columns) for r in score(docs, train(x, labels)).collect()} for x in (docs, dealt))
        assert a.keys() == b.keys() and all(abs(x - y) < 1e-9 for k in a for x, y in zip(a[k], b[k], strict=True))


def test_the_metadata_view_does_not_read_the_text(spark):
    """Two texts with the same metadata have one metadata score, whatever they say."""
    sf = "/root/testdata/sf0.01"
    docs = given(spark, sf)
    model = cotrain.train(docs, given(spark, sf, "labels"))
    same = spark.createDataFrame([(1, "#### $$$$ BUY NOW !!!! " * 9, "en", "src1", 900), (2, "A quiet story of a house by the sea. " * 9, "en", "src1", 900)], docs.schema)
    a, b = cotrain.score(same, model).orderBy("doc_id").collect()
    assert a.meta_score == b.meta_score and a.text_score != b.text_score


# ---- 7 sharding ------------------------------------------------------------------------------


def brute_best_fit(sizes, capacity):
    bins, out = [], [0] * len(sizes)
    for i in sorted(range(len(sizes)), key=lambda i: (-sizes[i], i)):
        fit = [(room, k) for k, room in enumerate(bins) if room >= sizes[i]]
        if not fit:
            bins.append(capacity)
            fit = [(capacity, len(bins) - 1)]
        room, k = min(fit)
        bins[k] = room - sizes[i]
        out[i] = k
    return out


def runs_of(sizes):
    return sorted(collections.Counter(sizes).items(), reverse=True)


def test_best_fit_by_brute_force():
    rng = random.Random(5)
    for _ in range(60):
        sizes = sorted((rng.randrange(1, 50) for _ in range(rng.randrange(1, 200))), reverse=True)
        spans, opened = sharding.best_fit_decreasing(runs_of(sizes), 60)
        assert [k for _, k, n in spans for _ in range(n)] == brute_best_fit(sizes, 60) and opened == max(brute_best_fit(sizes, 60)) + 1
    with pytest.raises(ValueError):
        sharding.best_fit_decreasing([(9, 1)], 8)


def group_sizes(rows):
    """Bytes of each group of equal texts, largest first."""
    count = collections.Counter(r.text or "" for r in rows)
    return sorted(((len(t.encode()) + 1) * n for t, n in count.items()), reverse=True)


def test_fixed_capacity_by_brute_force(spark, sf):
    docs = given(spark, sf).select("doc_id", "text").unionByName(odd(spark).select("doc_id", "text"))
    sizes = group_sizes(docs.collect())
    capacity = 2 * sizes[0]
    load = collections.Counter()
    for k, s in zip(brute_best_fit(sizes, capacity), sizes, strict=True):
        load[k] += s
    got = collections.Counter()
    for r in sharding.shard(docs, None, capacity).collect():
        got[r.shard] += r.size
    assert got == load and max(got.values()) <= capacity
    with pytest.raises(ValueError):
        sharding.shard(docs, None, sizes[0] - 1)


def test_equal_shards_by_brute_force(spark, sf, monkeypatch):
    """The groups of the whole table are packed as best fit packs them one by one, joined by broadcast or by shuffle."""
    docs = given(spark, sf).select("doc_id", "text")
    docs = docs.unionByName(docs.limit(30)).unionByName(spark.createDataFrame([(-1, "same")] * 300, docs.schema))
    sizes = group_sizes(docs.collect())
    for bound in (500_000, 10):
        monkeypatch.setattr(sharding, "BROADCAST_ROWS", bound)
        got = collections.Counter()
        for r in sharding.shard(docs, 8).collect():
            got[r.shard] += r.size
        load = collections.Counter()
        for k, s in zip(brute_best_fit(sizes, max(got.values())), sizes, strict=True):
            load[k] += s
        assert got == load and len(got) == 8


def test_shards(spark, sf):
    docs = given(spark, sf).select("doc_id", "text").unionByName(odd(spark).select("doc_id", "text"))
    out = sharding.shard(docs, 8).collect()
    rows = docs.collect()
    assert collections.Counter((r.doc_id, r.size, r.text_crc32) for r in out) == collections.Counter((r.doc_id, len((r.text or "").encode()) + 1, zlib.crc32((r.text or "").encode())) for r in rows)
    for k in range(8):
        assert sorted(r.slot for r in out if r.shard == k) == list(range(sum(r.shard == k for r in out)))
    by_text = collections.defaultdict(set)
    for r in out:
        by_text[r.text_crc32, r.size].add(r.shard)
    assert all(len(v) == 1 for v in by_text.values())
    sizes = [sum(r.size for r in out if r.shard == k) for k in range(8)]
    assert max(sizes) - min(sizes) < 0.02 * sum(sizes) / 8 + 1000
    assert sharding.shard(empty(spark)).count() == 0


def test_a_group_over_a_fair_share_is_alone():
    spans = sharding.pack([(1000, 1), (10, 100)], 4)
    load = collections.Counter()
    for i, k, n in spans:
        load[k] += (1000, 10)[i] * n
    assert load[0] == 1000 and max(load[k] for k in (1, 2, 3)) - min(load.values()) <= 20 and sum(load.values()) == 2000


def test_shards_beside_clashing_columns(spark):
    docs = odd(spark).selectExpr("*", "'x' as `group`", "1 as size", "2 as at", "3 as part", "4 as bytes")
    out = sharding.shard(docs, 3)
    assert out.columns == ["doc_id", "size", "text_crc32", "shard", "slot"] and out.count() == len(ODD)


# ---- 8 token ids -----------------------------------------------------------------------------


@pytest.fixture(scope="module")
def word_model():
    import public_tokenizers

    return public_tokenizers.path("word_bpe_49k.json")


def test_word_encoder_equals_the_pipeline(word_model):
    from tokenizers import Tokenizer

    t = Tokenizer.from_file(word_model)
    rng = random.Random(8)
    alphabet = [chr(c) for c in itertools.chain(range(32, 127), range(0xA0, 0x250), (0x301, 0x307, 0x331, 0x1E9E, 0x3A3, 0x130, 0x65E5, 0x1F642))] + [" "] * 60 + ["<|endoftext|>", ".", ",", "\n", "'s"]
    texts = ["".join(rng.choices(alphabet, k=rng.randrange(60))) for _ in range(3000)] + [r[1] for r in ODD]
    ids, n = repair.WordEncoder(word_model).encode(pa.array(texts))
    at = np.concatenate([[0], np.cumsum(n)])
    for i, x in enumerate(texts):
        assert ids[at[i] : at[i + 1]].tolist() == t.encode(x or "", add_special_tokens=False).ids, repr(x)


def test_grammar_round_trip_and_random_access():
    rng = np.random.default_rng(0)
    for n in (0, 1, 50, 5000, 60_000):
        ids = rng.choice(np.arange(40), n, p=np.arange(40, 0, -1) / 820).astype(np.uint32)
        ids[n // 2 :] = ids[: n - n // 2] if n else ids
        seq, rules, size = repair.compress(ids, 50)
        assert (repair.expand(seq, rules, 50) == ids).all() and (n < 5000 or len(seq) < n)
        shard = repair.Shard(repair.pack_shard(seq, rules, size, np.array([n // 3, n - n // 3]), 50))
        assert (shard.document(0) == ids[: n // 3]).all() and (shard.document(1) == ids[n // 3 :]).all()
        for _ in range(20):
            a, b = sorted(rng.integers(0, n + 1, 2))
            assert (shard.range(int(a), int(b)) == ids[a:b]).all()
    same = np.full(1001, 7, np.uint32)
    assert (repair.expand(*repair.compress(same, 8)[:2], 8) == same).all()


def most_frequent_pair(seq):
    """Occurrences of the most frequent pair; in a run of one symbol every other pair counts."""
    counts, before = collections.Counter(), None
    for at, pair in enumerate(itertools.pairwise(seq)):
        if before == (at - 1, pair):
            before = None
            continue
        counts[pair] += 1
        before = (at, pair)
    return max(counts.values())


@pytest.mark.parametrize("least", [2, 4, 16])
def test_no_frequent_pair_is_left(least):
    rng = np.random.default_rng(4)
    phrases = [rng.integers(0, 40_000, int(rng.integers(2, 40))) for _ in range(4000)]
    ids = np.concatenate([phrases[int(i)] for i in (4000 * rng.random(30_000) ** 2).astype(int)] + [np.full(999, 5)])
    seq, rules, size = repair.compress(ids, 40_000, least)
    assert most_frequent_pair(seq.tolist()) < least and len(rules) > 4096
    # every rule pays for itself and is made of what came before it
    assert (rules.max(axis=1) < 40_000 + np.arange(len(rules))).all() and size.min() >= 2
    assert (repair.expand(seq, rules, 40_000) == ids).all()


def test_a_long_repeated_passage_takes_few_rules():
    """Pairs of equal counts are paired up all along: the grammar of n copies of a passage is about as long as the passage."""
    passage = np.arange(5000)
    ids = np.tile(passage, 8)
    seq, rules, size = repair.compress(ids, 5000)
    assert len(rules) <= 5001 and len(seq) <= 16 and (repair.expand(seq, rules, 5000) == ids).all()


def test_ids_written_and_read(spark, sf, word_model, tmp_path):
    from tokenizers import Tokenizer

    t = Tokenizer.from_file(word_model)
    docs = given(spark, sf).select("doc_id", "text").unionByName(odd(spark, [r for r in ODD if r[0] is not None and r[0] > 1][:3]).withColumn("doc_id", common.F.col("doc_id") + 100_000).select("doc_id", "text"))
    path = str(tmp_path / "ids")
    repair.write_ids(docs, path, word_model, 2)
    got = {r.doc_id: (r.start, r.n_tokens, r.ids_crc32) for r in repair.read_documents(spark, path).collect()}
    start, want = 0, {}
    for r in sorted(docs.collect(), key=lambda r: r.doc_id):
        ids = [*t.encode(r.text or "", add_special_tokens=False).ids, 2]
        want[r.doc_id] = (start, len(ids), zlib.crc32(np.array(ids, "<u4").tobytes()))
        start += len(ids)
    assert got == want
    one = repair.fetch(spark, path, 100_002)
    assert [x.tolist() for x in one] == [[2]]


def test_ids_of_odd_rows(spark, word_model, tmp_path):
    repair.write_ids(odd(spark), str(tmp_path / "a"), word_model)
    assert repair.read_documents(spark, str(tmp_path / "a")).count() == len(ODD)
    repair.write_ids(empty(spark), str(tmp_path / "b"), word_model)
    assert repair.read_documents(spark, str(tmp_path / "b")).count() == 0


# ---- 10 licences -----------------------------------------------------------------------------


def test_licences(spark, sf):
    from pyspark.sql import functions as F

    docs = given(spark, sf.replace("0.001", "0.01"))
    model = licences.train(docs)
    lines = ["Licensed under the Apache License, Version 2.0.", "Released under the MIT License.", "Licensed under CC BY-NC 4.0.", "This work is licensed under the GNU General Public License, version 3."]
    rows = [(i, f"Some words here.\n{x}\nMore of it.") for i, x in enumerate(lines)] + [(9, "the licence plate of the car was general and public"), (10, None), (11, ""), (12, "\n".join(lines[:2]))]
    out = {r.doc_id: r for r in licences.scan(spark.createDataFrame(rows, "doc_id bigint, text string"), model).collect()}
    assert [out[i].families for i in range(4)] == [["Apache"], ["MIT"], ["CC-BY-NC"], ["GPL"]]
    assert out[9].families == out[10].families == out[11].families == [] and out[12].families == ["Apache", "MIT"]
    n = out[0].notices[0]
    assert rows[0][1].encode()[n.start : n.end].decode() == lines[0] and 0.5 <= n.probability <= 1
    found = licences.scan(docs, model).join(docs.select("doc_id", "text"), "doc_id")
    assert found.where((F.size("families") > 0) & ~F.col("text").rlike("(?i)licen[sc]e|copyright|CC BY")).count() == 0
    assert licences.scan(odd(spark), model).count() == len(ODD) and licences.scan(empty(spark), model).count() == 0
    # recall on all lines of the table that are notices, the shortest among them
    notices = found.where(F.col("text").rlike(r"(?i)\bAll rights reserved\.|under the (MIT|Apache|GNU)|under CC BY|SPDX-License"))
    assert notices.count() > 30 and notices.where(F.size("families") > 0).count() >= 0.95 * notices.count()


def test_licences_inside_long_and_wrapped_paragraphs(spark, sf):
    docs = given(spark, sf.replace("0.001", "0.01"))
    model = licences.train(docs)
    pool = [w for r in docs.select("text").where("text is not null").orderBy("doc_id").limit(50).collect() if not re.search(r"(?i)licen[sc]e|copyright|reserved|CC", r.text) for w in r.text.split()]
    notices = {"Apache": "Licensed under the Apache License, Version 2.0.", "MIT": "Released under the MIT License.", "CC-BY-NC": "Licensed under CC BY-NC 4.0.", "GPL": "This work is licensed under the GNU General Public License, version 3."}
    rng, rows, want = random.Random(2), [], {}
    for f, x in notices.items():
        for n in (20, 50, 300, 2000):
            for wrap in (False, True):
                at = rng.randrange(n)
                filler = rng.choices(pool, k=n)
                said = x.replace("nder ", "nder\n", 1) if wrap else x
                rows.append((len(rows), " ".join([*filler[:at], said, *filler[at:]])))
                want[rows[-1][0]] = ([f], said)
    rows += [(900, " ".join([*pool[:40], *notices.values(), *pool[40:80]])), (901, " ".join(rng.choices(pool, k=3000))), (902, "Licensed under the Apache\n\nstory of a general and public version")]
    out = {r.doc_id: r for r in licences.scan(spark.createDataFrame(rows, "doc_id bigint, text string"), model).collect()}
    text = dict(rows)
    for i, (families, said) in want.items():
        assert out[i].families == families and len(out[i].notices) == 1, (i, text[i][:200])
        n = out[i].notices[0]
        assert text[i].encode()[n.start : n.end].decode().rstrip(".") == said.rstrip(".")
    assert out[900].families == sorted(notices) and out[901].families == []


def test_digest_of_items():
    assert hashlib.sha256(b"").hexdigest() == "e3b0c44298fc1c149afbf4c8996fb92427ae41e4649b934ca495991b7852b855"
