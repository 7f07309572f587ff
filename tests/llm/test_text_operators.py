"""Each operator against a brute-force form, on rows that are null, empty, long, tied, repeated or absent, with columns whose names clash."""

import hashlib
import re
import time
import zlib
from collections import Counter, defaultdict

import numpy as np
import pyarrow as pa
import pytest
from hypothesis import given, settings, strategies as st

from rangevec.llm import exact_dedup, licenses, lm, minhash, mixing, packing
from rangevec.llm.queries import remainder, tokenizer_path
from rangevec.llm.shared import Words

WORD = re.compile(r"[^\x20\x09-\x0D]+")
LOWER = str.maketrans("ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")
CLASH = "doc_id long, text string, source string, h string, n long, rep long, key string, size long, g int, row string, words string, part int"


def low(text):
    return (text or "").translate(LOWER)


def frame(spark, rows):
    """Rows (id, text) or (id, text, source) among columns that operators might use themselves."""
    full = [(r[0], r[1], r[2] if len(r) > 2 else "s", "x", 1, 2, "k", 3, 4, "r", "w", 5) for r in rows]
    return spark.createDataFrame(full, CLASH)


base = "alpha beta gamma delta epsilon zeta eta theta iota kappa lambda mu nu xi omicron pi rho sigma tau upsilon".split()
EDGE = [(1, None), (2, ""), (3, "  \n "), (4, "Word"), (5, "word"), (6, "É é"), (7, "é É"), (8, "long " * 60_000), (9, "tie tie tie"), (10, "tie tie tie"), (10, "tie tie tie"), (11, " ".join(base)), (12, " ".join(base[:-1] + ["omega"])), (13, " ".join(base).upper())]


@settings(max_examples=60, deadline=None)
@given(st.lists(st.one_of(st.none(), st.text(alphabet="aB \t\n\x0b\x1c\x85É ", max_size=12)), max_size=6))
def test_words(texts):
    w = Words(pa.array(texts, pa.string()))
    got = [[w.vocab[c] for c in w.codes[a:b]] for a, b in zip(w.offsets[:-1], w.offsets[1:], strict=True)]
    assert got == [WORD.findall(low(t)) for t in texts]


@pytest.mark.parametrize("bits", [128, 8])
@pytest.mark.parametrize("keep", ["min", "max"])
def test_exact(spark, bits, keep):
    rows = EDGE + [(100 + i, f"text {i % 40}") for i in range(400)]
    groups = defaultdict(list)
    for i, t in rows:
        groups[low(t)].append(i)
    pick = min if keep == "min" else max
    want = sorted((i, pick(groups[low(t)]), len(groups[low(t)]), i == pick(groups[low(t)]), hashlib.sha256(low(t).encode()).hexdigest()) for i, t in rows)
    got = exact_dedup.duplicate_groups(frame(spark, rows), keep=keep, bits=bits)
    assert sorted(map(tuple, got.collect())) == want
    assert exact_dedup.duplicate_groups(frame(spark, []), keep=keep).collect() == []


def test_exact_drop(spark):
    df = frame(spark, EDGE)
    out = exact_dedup.drop_duplicates(df)
    assert out.columns == df.columns
    assert sorted(r["doc_id"] for r in out.collect()) == [1, 3, 4, 6, 7, 8, 9, 11, 12]


TWICE = [(5, "A"), (5, "B"), (5, "B"), (3, "b"), (None, "c d"), (None, "e"), (None, "E"), (7, "c d"), (None, "f g h i j"), (6, "b b b b k"), (6, "q r s t u v"), (8, "Q R S T U V")]


def test_rows_without_an_id_of_their_own(spark):
    """Missing ids and one id with several texts: each text is a row of its own."""
    df = frame(spark, TWICE)
    texts = lambda out: sorted(((r["doc_id"], low(r["text"])) for r in out.collect()), key=str)
    once = sorted([(5, "a"), (3, "b"), (7, "c d"), (None, "e"), (None, "f g h i j"), (6, "b b b b k"), (6, "q r s t u v")], key=str)
    assert texts(exact_dedup.drop_duplicates(df)) == once
    near = minhash.near_duplicates(df)
    assert near.count() == len(TWICE)
    assert Counter((r["doc_id"], r["component_id"], r["kept"]) for r in near.collect()) == Counter([(5, 5, True), (5, 3, False), (5, 3, False), (3, 3, True), (None, 7, False), (None, None, True), (None, None, False), (7, 7, True), (None, None, True), (6, 6, True), (6, 6, True), (8, 6, False)])
    assert texts(minhash.drop_near_duplicates(df)) == once
    # One source takes all of itself.
    assert sorted(((r["doc_id"], r["text"]) for r in mixing.mixed_documents(df).collect()), key=str) == sorted(TWICE, key=str)


def naive_targets(sizes, cycle, most):
    names = sorted(sizes, key=lambda s: (s is None, s or ""))
    weight = {s: cycle[i % len(cycle)] for i, s in enumerate(names)}
    total, capped = sum(sizes.values()), {}
    while True:
        free = [s for s in names if s not in capped]
        left = total - sum(capped.values())
        share = {s: left * weight[s] / sum(weight[x] for x in free) for s in free}
        over = {s: most * sizes[s] for s in free if share[s] > most * sizes[s]}
        if not over:
            return {**capped, **share}
        capped |= over


def test_mixing(spark):
    rng = np.random.default_rng(1)
    rows = [(i, " ".join(["w"] * int(rng.integers(0, 60))), ["b", "a", None, "c", "d", "É"][i % 6] if i % 9 else "tiny") for i in range(900)] + [(9000, "x", "one"), (9001, None, "none")]
    got = mixing.mix(frame(spark, rows)).toPandas()
    again = mixing.mix(frame(spark, rows)).toPandas()
    assert got.sort_values("doc_id").reset_index(drop=True).equals(again.sort_values("doc_id").reset_index(drop=True))
    size = {r[0]: len(WORD.findall(r[1] or "")) for r in rows}
    source = {r[0]: r[2] for r in rows}
    sizes = Counter()
    for i, n in size.items():
        sizes[source[i]] += n
    want = naive_targets(sizes, (5, 2, 1), 3)
    taken = Counter()
    for r in got.itertuples():
        s = source[r.doc_id]
        assert r.size == size[r.doc_id] and r.source_size == sizes[s] and abs(r.target - want[s]) < 1e-6 and 0 <= r.taken <= 3 * r.size
        taken[s] += r.taken
    for s, n in taken.items():
        assert abs(n - want[s]) <= 2
    assert mixing.mix(frame(spark, [])).collect() == []
    mixed = mixing.mixed_documents(frame(spark, rows))
    assert mixed.columns == frame(spark, []).columns
    copies = Counter(r["doc_id"] for r in mixed.collect())
    assert all(copies[r.doc_id] == (-(-r.taken // r.size) if r.size else 0) for r in got.itertuples())


def test_apportion(spark):
    from pyspark.sql import functions as F

    rng = np.random.default_rng(0)
    for n in (1, 2, 7):
        claims, seats = rng.random(n) * 100, int(rng.integers(0, 50))
        got = [0] * n
        for _ in range(seats):
            k = max(range(n), key=lambda i: (claims[i] / (2 * got[i] + 1), -i))
            got[k] += 1
        df = spark.createDataFrame([(0, i, float(c)) for i, c in enumerate(claims)], "one int, k int, claim double").withColumn("seats", F.lit(seats)).withColumn("cap", F.lit(1000))
        out = mixing.apportion(df, ["one"], "k", "claim", "seats", "cap").orderBy("k").collect()
        assert [r["got"] for r in out] == got


def test_packing(spark):
    from tokenizers import Tokenizer

    rows = EDGE + [(200 + i, " ".join(base[: 1 + i % 20]) + " don't STOP, 3½ é̂ İ I\u0307 Å." * (i % 7)) for i in range(200)]
    rows += [(None, "no id"), (900, "ends <|endoftext|> here <|ENDOFTEXT|> A|b x|"), (901, "<|startoftext|>"), (902, "Mixed.CASE Word! word? WORD: \x1c odd\u00a0space")]
    path = tokenizer_path()
    t = Tokenizer.from_file(path)
    want = Counter()
    for i, text in rows:
        ids = t.encode(text or "", add_special_tokens=False).ids + [2]
        want[(i, tuple(ids))] += 1
    got = packing.pack(frame(spark, rows), path, group_pieces=64).toPandas()
    whole = {(i or -1, len(ids)): ids for i, ids in want}
    got["doc_id"] = got.doc_id.fillna(-1).astype(int)
    for r in got.itertuples():
        ids = np.array(whole[(r.doc_id, r.doc_tokens)][r.start : r.start + r.length], "<u4")
        assert len(ids) == r.length and zlib.crc32(ids.tobytes()) == r.ids_crc32
    assert got.length.sum() == sum(len(ids) * n for (_, ids), n in want.items())
    for _, s in got.groupby("sequence_id"):
        s = s.sort_values("offset")
        assert s.length.sum() <= 4096 and s.offset.tolist() == (s.length.cumsum() - s.length).tolist()
    assert packing.pack(frame(spark, []), path).collect() == []
    # A vocabulary that looks across white space is read text by text.
    other, few = tokenizer_path("byte_bpe_50k.json"), rows[-30:]
    t = Tokenizer.from_file(other)
    want = {(i, zlib.crc32(np.array([*t.encode(text or "", add_special_tokens=False).ids, 2], "<u4").tobytes())) for i, text in few}
    assert {(r["doc_id"], r["ids_crc32"]) for r in packing.pack(frame(spark, few), other).collect()} == want


def test_many_pieces_above_half_a_window():
    """Such pieces share no window, however many there are."""
    assert len(packing.pack_group([2049] * 700, 4096)) == 700
    assert len(packing.pack_group([2049] * 100 + [2047] * 100, 4096)) == 100


@settings(max_examples=80, deadline=None)
@given(st.lists(st.integers(1, 100), min_size=1, max_size=40), st.integers(1, 12))
def test_differencing(sizes, k):
    groups = packing.differencing(sizes, k)
    assert sorted(i for g in groups for i in g) == list(range(len(sizes))) and len(groups) <= k
    windows = packing.pack_group(sizes, 100)
    assert sorted(i for g in windows for i in g) == list(range(len(sizes))) and max(sum(sizes[i] for i in g) for g in windows) <= 100


def test_differencing_balances():
    rng = np.random.default_rng(0)
    sizes = rng.integers(100, 1500, 600).tolist()
    loads = [sum(sizes[i] for i in g) for g in packing.differencing(sizes, 40)]
    assert max(loads) - min(loads) < 20


def brute_components(rows, k, percent=80):
    sets = []
    for _, t in rows:
        w = WORD.findall(low(t))
        sets.append({tuple(w[i : i + k]) for i in range(len(w) - k + 1)} if len(w) >= k else {tuple(w)} if w else set())
    comp = {i: i for i, _ in rows}
    edges = [(rows[a][0], rows[b][0]) for a in range(len(rows)) for b in range(a) if sets[a] and sets[b] and 100 * len(sets[a] & sets[b]) >= percent * len(sets[a] | sets[b])]
    changed = True
    while changed:
        changed = False
        for a, b in edges:
            m = min(comp[a], comp[b])
            if comp[a] != m or comp[b] != m:
                comp[a] = comp[b] = m
                changed = True
    return {i: (len(s), comp[i]) for (i, _), s in zip(rows, sets, strict=True)}


@pytest.mark.parametrize("k", [4, 5])
def test_minhash(spark, k):
    rng = np.random.default_rng(2)
    vocab = [f"w{i}" for i in range(400)]
    rows = list(EDGE)
    for g in range(6):
        text = rng.choice(vocab, 120).tolist()
        for c in range(40):
            own = list(text)
            # Copies lie on both sides of the bound, so a group holds several components.
            for p in rng.integers(0, 120, int(rng.integers(0, 9))):
                own[p] = rng.choice(vocab)
            rows.append((1000 + 100 * g + c, " ".join(own)))
    want = brute_components(rows, k)
    got = {r["doc_id"]: (r["n_shingles"], r["component_id"], r["kept"]) for r in minhash.near_duplicates(frame(spark, rows), shingle=k).collect()}
    assert got == {i: (n, c, i == c) for i, (n, c) in want.items()}
    assert len({c for _, c in want.values()}) > 20
    assert minhash.near_duplicates(frame(spark, [])).collect() == []
    assert minhash.near_duplicates(frame(spark, [(1, None), (2, "")])).count() == 2
    kept = minhash.drop_near_duplicates(frame(spark, rows), shingle=k)
    assert kept.columns == frame(spark, []).columns and {r["doc_id"] for r in kept.collect()} == {i for i, (_, c) in want.items() if i == c}


def test_licenses(spark):
    cut = re.compile("[^\x00-\x2f\x3a-\x60\x7b-\x7f]+")
    phrases = {"mit": "under the mit license", "apache-2": "apache license version 2", "cc-by-nc": "cc by nc"}
    rows = EDGE + [
        (20, "Released under the MIT License."), (21, "under the mit licenses"), (22, "CC-BY-NC cc by nc CC BY NC 4.0, under the-MIT license"), (23, "the apache license, version 2.0 Apache License Version 2"), (24, "GNU General Public License, version 3."),
        (25, "x under the\nmit\tlicense é"), (26, "mit mit mit"), (27, "Permission is hereby granted, free of charge, to any human getting a copy of this software and associated documentation files"), (28, "under themit license"), (29, "cc by nc by nc"),
    ]
    got = {}
    for r in licenses.scan(frame(spark, rows)).collect():
        got.setdefault(r["doc_id"], r)
    for i, t in rows:
        words = cut.findall(low(t))
        places = [(a, label) for label, p in phrases.items() for a in range(len(words)) if words[a : a + len(p.split())] == p.split()]
        r = got[i]
        assert (r["n_words"], r["n_base"], r["first_word"], r["last_word"]) == (len(words), len(places), min((a for a, _ in places), default=None), max((a for a, _ in places), default=None)), t
        assert r["base_labels"] == ",".join(sorted({x for _, x in places})) and set(r["base_labels"].split(",")) - {""} <= set(r["labels"].split(","))
        assert 0 <= r["score"] <= 1
    assert got[24]["labels"] == "gpl-3" and got[27]["labels"] == "mit" and 0.8 <= got[27]["score"] < 1
    assert licenses.scan(frame(spark, [])).collect() == []


def brute_lm(rows, learn, order):
    tokens = {n: [*WORD.findall(low(t)), None] for n, (_, t) in enumerate(rows)}
    uni, bi, tri, follows, kinds, kinds3, preceded = Counter(), Counter(), Counter(), defaultdict(set), defaultdict(Counter), defaultdict(Counter), defaultdict(set)
    docs = 0
    for n, own in tokens.items():
        if learn(rows[n][0]):
            docs += 1
            uni.update(own)
            for a, b in zip(["<begin>", *own[:-1]], own, strict=True):
                bi[(a, b)] += 1
                follows[b].add(a)
            for a, b, c in zip(["<begin>", *own[:-2]], own[:-1], own[1:], strict=True) if len(own) > 1 else ():
                tri[(a, b, c)] += 1
                preceded[(b, c)].add(a)
    seen = Counter(bi)
    if order == 3:
        bi = {k: len(preceded[k]) if k[0] != "<begin>" else c for k, c in seen.items()}
    ctx = Counter()
    for (a, _), c in bi.items():
        kinds[a][min(c, 3)] += 1
        ctx[a] += c
    for (a, b, _), c in tri.items():
        kinds3[(a, b)][min(c, 3)] += 1

    def cut(counts):
        n = [sum(c == i for c in counts) for i in range(1, 5)]
        if min(n) <= 0:
            return [0, 0.5, 0.75, 0.9]
        y = n[0] / (n[0] + 2 * n[1])
        return [0, *(min(max(k - (k + 1) * y * n[k] / n[k - 1], 0), k) for k in (1, 2, 3))]

    f = cut(tri.values())
    d, e = cut(bi.values()), cut([len(x) for x in follows.values()])
    big, v, total = sum(uni.values()), len(uni), sum(len(x) for x in follows.values())
    spare0 = sum(e[min(len(x), 3)] for x in follows.values()) / total / (v + 1) if total else 1 / (v + 1)

    def lower(w):
        n = len(follows.get(w, ()))
        return (max(n - e[min(n, 3)], 0) / total if total else 0) + spare0

    out = []
    for n, own in tokens.items():
        s = b = 0.0
        for i, w in enumerate(own):
            a = own[i - 1] if i else "<begin>"
            b += np.log10((uni.get(w, 0) + 1) / (big + v + 1))
            p = lower(w)
            if kinds[a]:
                c = bi.get((a, w), 0)
                p = max(c - d[min(c, 3)], 0) / ctx[a] + sum(d[k] * x for k, x in kinds[a].items()) / ctx[a] * p
            h = (own[i - 2] if i > 1 else "<begin>", a)
            if order == 3 and i and kinds3[h]:
                c = tri.get((*h, w), 0)
                p = max(c - f[min(c, 3)], 0) / seen[h] + sum(f[k] * x for k, x in kinds3[h].items()) / seen[h] * p
            s += np.log10(p)
        out.append((rows[n][0], len(own), sum(uni.get(w, 0) > 0 for w in own), big, b, s))
    return out


@pytest.mark.parametrize(("learned", "order", "part"), [(True, 2, None), (True, 3, None), (True, 3, 40), (False, 3, None)])
def test_lm(spark, learned, order, part, monkeypatch):
    if part:
        monkeypatch.setattr(lm, "PART_TOKENS", part)
    rng = np.random.default_rng(4)
    vocab = [f"w{i}" for i in range(60)]
    rows = EDGE + [(1000 + i, " ".join(rng.choice(vocab, int(rng.integers(0, 40)), p=np.arange(60, 0, -1) / 1830))) for i in range(300)]
    # Counts and numbers of followers that a byte does not hold.
    rows += [(2000 + i, "a " * 300 + " ".join(f"x y z{j}" for j in range(300))) for i in range(3)]
    df = frame(spark, rows)
    learn = lambda i: learned and zlib.crc32(str(i).encode()) % 7 != 2
    from pyspark.sql import functions as F

    got = lm.score(df, lm.fit(df, (remainder(7) != 2) & F.lit(learned), order=order)).collect()
    want = sorted(brute_lm(rows, learn, order))
    have = sorted((r["doc_id"], r["n_tokens"], r["n_known"], r["train_tokens"], r["base_score"], r["score"]) for r in got)
    assert [h[:4] for h in have] == [w[:4] for w in want]
    assert np.allclose([h[4:] for h in have], [w[4:] for w in want], rtol=1e-9)
    assert lm.score(frame(spark, []), lm.fit(frame(spark, []), F.lit(True))).collect() == []


def test_lm_disk(spark):
    """A trigram takes five bytes and a share of its bigram's, and when all is counted the shuffles of the first two passes are gone."""
    from glob import glob
    from urllib.parse import urlparse

    from pyspark.sql import functions as F

    def shuffled():
        files = spark._jvm.org.apache.spark.SparkEnv.get().blockManager().diskBlockManager().getAllFiles().mkString("\n").split("\n")
        return {f.split("/shuffle_")[1].split("_")[0] for f in files if "/shuffle_" in f}

    rng = np.random.default_rng(5)
    rows = frame(spark, [(i, " ".join(f"w{j}" for j in rng.integers(0, 3000, 400))) for i in range(200)])
    old = shuffled()
    model = lm.fit(rows, F.lit(True))
    size = lambda name: sum(np.load(f).nbytes for f in glob(f"{urlparse(model.vocabulary.folder).path}/{name}-*.npy"))
    n, bigrams = size("triple_times"), int(model.pairs.first[-1])
    assert n > 75_000 and size("triples") + size("starts") <= 4 * n + bigrams
    # The trigrams' pass has two shuffles, those before it three.
    until = time.monotonic() + 10
    while len(shuffled() - old) > 2 and time.monotonic() < until:
        time.sleep(0.1)
    assert len(shuffled() - old) <= 2
