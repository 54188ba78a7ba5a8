"""Each operator against a brute-force version, and the defined results of odd inputs."""

import json
import hashlib
import os
import random
import re
import zlib
from collections import Counter, defaultdict

import numpy as np
import pytest

from arealex.llm import extraction, fingerprints, language, linededup, mixing, neardup, packing, quality, secrets, toxicity

SF = "/root/testdata/sf0.001"
DOC = "doc_id long, text string, lang string, source string, n_chars long"


@pytest.fixture(scope="module")
def docs(spark):
    return spark.read.parquet(f"{SF}/documents.parquet")


@pytest.fixture(scope="module")
def texts(docs):
    return {r.doc_id: r.text for r in docs.collect()}


def odd_rows():
    """Nulls, empty and white texts, ties, repeated rows, a long text."""
    return [
        (1, None, "en", "a", 0),
        (2, "", None, None, 0),
        (3, " \n\t\x0b\n", "en", "a", 5),
        (4, "one two three four", "en", "a", 18),
        (5, "ONE two three FOUR", "en", "b", 18),
        (6, "word " * 30000, "en", "b", 150000),
        (6, "word " * 30000, "en", "b", 150000),
        (7, "ünï çödé 漢字 🙂 text with a password: hunter22abc", "fr", None, 40),
        (8, "the line that is long enough to be looked at\n" * 3, "en", "a", 1),
        (None, "the line that is long enough to be looked at", "en", "a", 1),
    ]


@pytest.fixture(scope="module")
def odd(spark):
    from pyspark.sql import functions as F

    # Extra columns whose names could clash with the operators' own.
    extra = {c: F.lit(1) for c in ("id", "size", "k1", "key", "component", "cluster", "n", "value", "row", "kept", "target", "host", "line", "line_no", "score", "turn", "class")}
    return spark.createDataFrame(odd_rows(), DOC).withColumns(extra)


@pytest.fixture(scope="module")
def empty(odd):
    return odd.where("1 = 0")


WORD = re.compile(r"[^\x20\x09-\x0D]+")


def base_counts(t):
    t = t or ""
    w = WORD.findall(t)
    c = Counter(zip(w, w[1:], w[2:], strict=False))
    marked = {i + k for i in range(len(w) - 2) if c[tuple(w[i : i + 3])] > 1 for k in range(3)}
    lines = [x for x in t.split("\n") if WORD.search(x)]
    return len(w), sum(map(len, w)), len(re.findall(r"[#*$%&|<>]", t)), len(lines) - len(set(lines)), len(marked)


def test_quality(docs, odd, empty, texts):
    for table, want in ((docs, texts), (odd, None)):
        for r in quality.measure(table).collect():
            t = want[r.doc_id] if want else next(x[1] for x in odd_rows() if x[0] == r.doc_id)
            n, *rest = base_counts(t)
            assert (r.n_words, r.word_chars, r.n_symbols, r.n_dup_lines, r.n_repeat_words) == (n, *rest)
            assert r.base_failed == (n < 50 or 100 * rest[-1] > 50 * n)
            assert not (r.base_failed and r.kept)
    assert quality.measure(empty).count() == 0
    assert quality.keep(docs).columns == docs.columns and 0 < quality.keep(docs).count() < docs.count()
    assert quality.keep(odd).columns == odd.columns


def test_packing_round_trip(docs, odd, empty, texts):
    encode = packing.load_encoder(packing.default_vocabulary())
    from tokenizers import Tokenizer

    tok = Tokenizer.from_file(packing.default_vocabulary())
    for t in [*list(texts.values())[:60], "a  b\n\n c<|endoftext|>d 'll 漢字 🙂", ""]:
        assert list(encode(t)) == tok.encode(t, add_special_tokens=False).ids
    for table, rows in ((docs, list(texts.items())), (odd, [(r[0], r[1]) for r in odd_rows()])):
        pieces = packing.pack(table, open_windows=4).collect()
        ids = {d: np.array([*encode(t or ""), 1], "<u4") for d, t in rows}
        covered = Counter()
        for p in pieces:
            own = ids[p.doc_id]
            assert p.doc_tokens == len(own) and p.ids_crc32 == zlib.crc32(own[p.start : p.start + p.length].tobytes())
            covered[p.doc_id] += p.length
        times = Counter(d for d, _ in rows)
        assert covered == Counter({d: len(v) * times[d] for d, v in ids.items()})
        sequences = defaultdict(list)
        for p in pieces:
            sequences[p.sequence_id].append((p.offset, p.length))
        for s in sequences.values():
            at = 0
            for offset, length in sorted(s):
                assert offset == at
                at += length
            assert at <= 2048
    assert packing.padding(packing.pack(docs)).first().padding_share < 0.05
    assert packing.pack(empty).count() == 0


def test_packing_of_long_runs():
    encode = packing.load_encoder(packing.default_vocabulary())
    from tokenizers import Tokenizer

    tok = Tokenizer.from_file(packing.default_vocabulary())
    for t in (" " * 1_200_000, "\n" * 200_000 + "x", "a" * 100_000, "x" + "\t \n" * 400_000 + "y"):
        assert list(encode(t)) == tok.encode(t, add_special_tokens=False).ids


def test_language_by_brute_force(docs):
    """Vectors, cosines and the nearest centroid by plain loops over dictionaries of grams."""
    from math import log, sqrt

    rows = docs.where("lang is not null and text is not null").orderBy("doc_id").limit(40).collect()
    model = language.fit({k: [r.text for r in rows if r.lang == k] for k in {r.lang for r in rows}}, per_language=2)
    size, m = len(model.idf), (1 << 32) - 1

    def mixed(c):
        x = (c + 1) * 0x9E3779B1 & m
        return x ^ x >> 15

    for t in [r.text for r in rows[:12]] + ["Ünder  den 12 Brücken!", "x"]:
        letters, last = [], None
        for ch in t.lower():
            c = 32 if ord(ch) < 170 and not "a" <= ch <= "z" else ord(ch)
            if not (c == 32 and last == 32):
                letters.append(c)
            last = c
        letters = [32, *letters, 32]
        counts = Counter()
        for n in (1, 2, 3):
            for k in range(len(letters) - n + 1):
                h = mixed(letters[k])
                for c in letters[k + 1 : k + n]:
                    h = h * 0x01000193 & m ^ mixed(c)
                counts[(h * 0x85EBCA6B & m) >> 7] += 1
        vector = Counter()
        for h, n in counts.items():
            vector[h % size] += n
        vector = {k: log(1 + n) * float(model.idf[k]) for k, n in vector.items()}
        norm = sqrt(sum(v * v for v in vector.values()))
        cos = [sum(v * float(c[k]) for k, v in vector.items()) / norm for c in model.matrix]
        lang, score, best, rejected = model.predict([t])[0]
        assert abs(best - max(cos)) < 1e-4 and lang == model.langs[cos.index(max(cos))] and 0 <= score <= 1
        assert rejected == (best < model.floor[cos.index(max(cos))])


def test_language_rejects_what_is_far(docs):
    model = language.train(docs)
    own = [r.text for r in docs.where("lang is not null").collect()]
    far = ["漢字 仮名 交じり 文 の 例" * 5, "zzqx qqzv xxqz vvzq " * 8, "Ωμέγα άλφα βήτα γάμμα"]
    assert sum(x[3] for x in model.predict(own)) <= 0.03 * len(own)
    assert all(x[3] for x in model.predict(far))


def test_language(docs, odd, empty):
    held = "pmod(crc32(cast(cast(doc_id as string) as binary)), 4) = 2"
    model = language.train(docs.where(f"not ({held})"))
    got = language.identify(docs.where(held), model).join(docs.select("doc_id", "lang"), "doc_id").collect()
    assert sum(r.lang == r.lang_pred for r in got) >= 0.95 * len(got)
    rows = {r.doc_id: r for r in language.identify(odd, model).collect()}
    assert all(rows[k].lang_pred == "und" and rows[k].score == 0 for k in (1, 2, 3))
    assert language.identify(empty, model).count() == 0
    assert language.train(empty).predict(["some text"])[0][0] == "und"


def test_language_learns_very_long_texts():
    texts = {"xa": ["alpha beta gamma delta " * 25_000, "alpha beta gamma"], "xb": ["omicron sigma upsilon " * 30, "sigma omicron"]}
    model = language.fit(texts)
    assert np.isfinite(model.matrix).all() and np.isfinite(model.floor).all()
    got = model.predict(["beta gamma delta alpha", "upsilon sigma omicron", texts["xa"][0]])
    assert [x[0] for x in got] == ["xa", "xb", "xa"] and all(np.isfinite(x[1:3]).all() for x in got)


def test_language_learns_every_value(spark):
    # 70 languages of their own letters; ids repeat in one of them.
    word = lambda k: "".join(chr(0x4E00 + 40 * k + j) for j in range(20))
    rows = [(10 * k + j, word(k)[j:] + f" {j}", f"l{k:02}") for k in range(70) for j in range(3)] + [(5, word(0), "l00")] * 30
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string")
    found = language.sample(docs, 2, 512)
    assert sorted(found) == sorted({r[2] for r in rows}) and all(len(v) == 2 for v in found.values())
    model = language.train(docs)
    assert [x[0] for x in model.predict([word(k) for k in range(70)])] == [f"l{k:02}" for k in range(70)]


def plain_components(n, link):
    label = list(range(n))

    def root(x):
        while label[x] != x:
            x = label[x]
        return x

    for a in range(n):
        for b in range(a + 1, n):
            if root(a) != root(b) and link(a, b):
                label[max(root(a), root(b))] = min(root(a), root(b))
    return [root(x) for x in range(n)]


def test_neardup(spark, docs, odd, empty, texts):
    def words(t):
        w = (t or "").encode().lower().split()
        return {tuple(w[i : i + 5]) for i in range(max(1, len(w) - 4))} if w else set()

    rng = random.Random(5)
    rows = dict(texts)
    base = [t for t in texts.values() if 100 < len(t.split()) < 300][:3]
    # A group larger than a block, from equal to far.
    for k in range(330):
        w = base[k % 3].split()
        for _ in range(rng.randrange(0, 12)):
            w[rng.randrange(len(w))] = f"x{rng.randrange(10**6)}"
        rows[10_000 + k] = " ".join(w)
    ids = sorted(rows)
    sets = [words(rows[i]) for i in ids]
    want = plain_components(len(ids), lambda a, b: bool(sets[a]) and 100 * len(sets[a] & sets[b]) >= 80 * len(sets[a] | sets[b]))
    frame = spark.createDataFrame([(i, rows[i]) for i in ids], "doc_id long, text string")
    got = {r.doc_id: r for r in neardup.near_duplicates(frame).collect()}
    for k, i in enumerate(ids):
        assert got[i].n_shingles == len(sets[k])
        assert got[i].component_id == ids[want[k]]
        assert got[i].kept == (got[i].component_id == i)
    found = sorted((str(r.doc_id), r.n_shingles, str(r.component_id), str(r.kept)) for r in neardup.near_duplicates(odd).collect())
    assert ("4", 1, "4", "True") in found and ("5", 1, "4", "False") in found and ("1", 0, "1", "True") in found
    assert found.count(("6", 1, "6", "True")) == 2 and len(found) == len(odd_rows())
    assert neardup.near_duplicates(empty).count() == 0


def test_mixing(docs, odd, empty):
    rows = mixing.mix(docs).collect()
    total, targets, taken = sum(r.size for r in rows), {}, Counter()
    for r in rows:
        targets[r.source] = (r.target, r.source_size)
        taken[r.source] += r.taken
        assert 0 <= r.taken <= 2 * r.size
    # Resharing by hand.
    names = sorted(targets)
    weight = {s: (5, 2, 1)[k % 3] for k, s in enumerate(names)}
    open_, left, want = set(names), 1.5 * total, {}
    while open_:
        level = left / sum(weight[s] for s in open_)
        above = {s for s in open_ if level * weight[s] > 2 * targets[s][1]}
        if not above:
            want |= {s: level * weight[s] for s in open_}
            break
        for s in above:
            want[s] = 2 * targets[s][1]
            left -= want[s]
        open_ -= above
    for s in names:
        assert abs(want[s] - targets[s][0]) < 1e-3
        assert abs(taken[s] - want[s]) <= max(30, 0.02 * want[s])
    assert sorted(map(str, rows)) == sorted(map(str, mixing.mix(docs.repartition(3)).collect()))
    assert mixing.mix(odd).count() == len(odd_rows()) and mixing.mix(empty).count() == 0
    again = mixing.mixed(docs)
    assert again.columns == docs.columns and again.count() == sum(r.taken // r.size for r in rows if r.size)
    assert mixing.mixed(odd).columns == odd.columns and mixing.mixed(empty).count() == 0


def test_mixing_rates_solve_the_dual(docs):
    """Rates are exp(m * size) up to the limit with one m a source, and meet the targets; m against bisection on all documents."""
    from math import exp, log

    by = defaultdict(list)
    for r in mixing.mix(docs).collect():
        by[r.source].append(r)
    for rows in by.values():
        t, rows = rows[0].target, [r for r in rows if r.size]
        assert abs(sum(r.rate * r.size for r in rows) - t) <= max(1, 1e-4 * t)
        whole, least = sum(r.size for r in rows), min(r.size for r in rows)
        low, high = (0.0, log(2) / least) if t > whole else (-log(whole / t) / least, 0.0)
        for _ in range(200):
            m = (low + high) / 2
            low, high = (m, high) if sum(r.size * min(2.0, exp(m * r.size)) for r in rows) < t else (low, m)
        assert t >= 2 * whole - 0.5 or all(abs(r.rate - min(2.0, exp(m * r.size))) < 1e-3 for r in rows)
        assert all(0 <= r.copies <= 2 for r in rows) and len({round(r.rate, 6) for r in rows}) > 1 or t >= 2 * whole - 0.5


def test_mixing_with_a_giant_document(spark):
    """19,000 words in short texts and 81,000 in one: the nearest mixes to 40,000 are 38,000 (short ones twice), to 90,000 are 100,000 less a tenth, to 10,000 all in short ones."""
    rows = [(k, "w " * 100, "a") for k in range(190)] + [(500, "w " * 81_000, "a")]
    docs = spark.createDataFrame(rows, "doc_id long, text string, source string")
    for percent, nearest in ((40, 38_000), (10, 10_000), (90, 90_000), (119, 119_000)):
        taken = sum(r.taken for r in mixing.mix(docs, share_percent=percent).collect())
        assert abs(taken - nearest) <= 0.01 * nearest


def test_mixing_passes_over_long_texts(spark):
    from pyspark.sql import functions as F

    def place(k):
        return hashlib.md5(str(k).encode()).hexdigest()

    order = sorted(range(3000), key=place)
    for wanted, at in ((25, 40), (25, 2900), (75, 2900), (75, 40)):
        # One text as long as all others, early or late in the order; one source, so it gets the whole share.
        rows = [(k, "w " * (30_000 if k == order[at] else 10), "a") for k in range(3000)]
        docs = spark.createDataFrame(rows, "doc_id long, text string, source string")
        got = mixing.mix(docs, share_percent=wanted).agg(F.first("target").alias("t"), F.sum("taken").alias("n"), F.max("copies").alias("c")).first()
        assert abs(got.t - got.n) <= 10 and got.c == 1


def test_secrets(docs, odd, empty, texts):
    for r in secrets.scan(docs.unionByName(odd.select(docs.columns))).collect():
        t = texts.get(r.doc_id)
        if t is None or r.doc_id <= 8:
            continue
        spans = [(m.start(), 0, m.end()) for m in re.finditer(secrets.ASSIGN, t) if len(m[2]) >= 6]
        spans += [(m.start(), 1, m.end()) for m in re.finditer(secrets.ACCESS, t) if len(m[0]) >= 20]
        spans += [(m.start(), 2, m.end()) for m in re.finditer(secrets.HEX, t) if len(m[0]) >= 24]
        joined = ",".join(f"{secrets.KINDS[k]}:{s}:{e}" for s, k, e in sorted(spans))
        assert r.base_sha256 == hashlib.sha256(joined.encode()).hexdigest()
        assert (r.n_assign, r.n_access, r.n_hex) == tuple(sum(k == j for _, k, _ in spans) for j in range(3))
        assert set(filter(None, joined.split(","))) <= set(r.spans.split(","))
    rows = {r.doc_id: r for r in secrets.scan(odd).collect()}
    assert rows[7].n_assign == 1 and rows[1].spans == "" and secrets.scan(empty).count() == 0


def test_secret_models():
    m = secrets.train(secrets.labelled_random(), secrets.labelled_ordinary(["the quick brown fox jumps over configuration values of several customers and their orders"] * 50))
    rng = random.Random(3)
    random_ones = ["".join(rng.choice(a) for _ in range(40)) for a in secrets.ALPHABETS.values() for _ in range(50)]
    plain = ["the_configuration_values", "customersAndTheirOrders", "brown-fox-jumps-over", "configurationcustomers"]
    assert sum(m.score(x) >= m.threshold for x in random_ones) >= 0.97 * len(random_ones)
    assert not any(m.score(x) >= m.threshold for x in plain)
    assert [e for *_, e in secrets.markov_spans(f"see {random_ones[-1]} there", m, [])] == [44]


def test_secrets_in_texts_of_many_spans():
    import time

    m = secrets.train(secrets.labelled_random(), secrets.labelled_ordinary(["values of several customers"] * 40))
    rng = random.Random(4)
    text = " ".join(f"password=pw{k}zzz some_ordinary_words_here_{k % 9} {''.join(rng.choice(secrets.ALPHABETS['base62']) for _ in range(20))}" for k in range(6000))
    base = secrets.base_spans(text)
    began = time.time()
    got = secrets.markov_spans(text, m, base)
    assert time.time() - began < 6
    # The same by comparing each token with each span, on the first part of the text.
    part = [x for x in base if x[2] < 20_000]
    want = [(x.start(), 3, x.end()) for x in secrets.TOKEN.finditer(text[:19_000]) if m.score(x[0]) >= m.threshold and not any(s < x.end() and x.start() < e for s, _, e in part)]
    assert want and got[: len(want) - 1] == want[:-1]


def test_secrets_held_out(spark, docs, texts):
    """Random strings of other seeds and lengths, planted in texts of the table: precision and recall of the added spans."""
    rng = np.random.default_rng(99)
    rows, planted = [], {}
    for d, t in list(texts.items())[:120]:
        if not t or secrets.base_spans(t):
            continue
        kind = ("base36", "base62", "base64")[d % 3]
        token = "".join(rng.choice(list(secrets.ALPHABETS[kind]), int(rng.integers(24, 48))))
        planted[d] = (len(t) + 1, len(t) + 1 + len(token))
        rows.append((d, f"{t} {token} and then the_configuration_of_several_customers"))
    frame = spark.createDataFrame(rows, "doc_id long, text string")
    found = secrets.scan(frame)
    hits = marked = 0
    for r in found.collect():
        own = [tuple(map(int, x.split(":")[1:])) for x in r.spans.split(",") if x.startswith("markov")]
        marked += len(own)
        hits += planted[r.doc_id] in own
    assert len(rows) > 50 and hits >= 0.95 * len(rows) and hits >= 0.9 * marked
    clean = {r.doc_id: r.text for r in secrets.redact(frame, found).collect()}
    for d, t in rows:
        a, b = planted[d]
        assert t[a:b] not in clean[d] or clean[d] == t
    assert sum("[SECRET]" in t for t in clean.values()) >= hits


def test_redaction_of_overlapping_spans(spark):
    docs = spark.createDataFrame([(1, "ab secret xyz end"), (2, None), (3, "left"), (4, "")], "doc_id long, text string")
    spans = spark.createDataFrame([(1, "assign:3:9,hex:5:13"), (2, ""), (4, None)], "doc_id long, spans string")
    assert {r.doc_id: r.text for r in secrets.redact(docs, spans).collect()} == {1: "ab [SECRET] end", 2: None, 3: "left", 4: ""}


def edits(a, b):
    p = list(range(len(b) + 1))
    for i, x in enumerate(a, 1):
        q = [i]
        for j, y in enumerate(b, 1):
            q.append(min(p[j] + 1, q[-1] + 1, p[j - 1] + (x != y)))
        p = q
    return p[-1]


def mutated(s, k, rng):
    s = list(s)
    for _ in range(k):
        i, what = rng.randrange(len(s) + 1), rng.randrange(3)
        if what == 0:
            s.insert(i, rng.choice("abcdefg "))
        elif s:
            s[min(i, len(s) - 1) : min(i, len(s) - 1) + 1] = [] if what == 1 else [rng.choice("abcdefg ")]
    return "".join(s)


def test_edit_distance():
    rng = random.Random(2)
    for _ in range(4000):
        a = "".join(rng.choice("abc") for _ in range(rng.randrange(14)))
        b = mutated(a, rng.randrange(7), rng)
        for tau in (1, 2, 5):
            assert linededup.within(a, b, tau) == (edits(a, b) <= tau)


def test_segment_keys_are_complete():
    rng = random.Random(4)
    for _ in range(1500):
        tau = rng.choice((1, 2, 3))
        a = "".join(rng.choice("abcdefgh") for _ in range(rng.randrange(12, 40)))
        b = mutated(a, rng.randrange(tau + 1), rng)
        n = np.array([len(a), len(b)])
        chars, begin = np.frombuffer((a + b).encode("utf-32-le"), np.uint32), np.array([0, len(a)])
        keys, owner = linededup.line_keys(n, chars, begin, tau)
        assert set(keys[owner == 0].tolist()) & set(keys[owner == 1].tolist())
        s = linededup.sketches(n, chars, begin)
        assert int(s[0] ^ s[1]).bit_count() <= 4 * tau


def test_linededup(spark, docs, odd, empty, texts, monkeypatch):
    rng = random.Random(9)
    rows = {k: t for k, t in list(texts.items())[:60]}
    seeds = ["".join(rng.choice("abcdefgh ") for _ in range(n)) for n in (24, 40, 90)]
    for k in range(150):
        rows[20_000 + k] = "\n".join([mutated(seeds[k % 3], rng.randrange(5), rng), "short", f"unique line number {rng.random()} here"])
    monkeypatch.setattr(linededup, "LONG_LIST", 12)
    monkeypatch.setattr(linededup, "BLOCK", 16)
    occurrences = [(d, k, x) for d in sorted(rows) for k, x in enumerate(rows[d].split("\n")) if len(x) >= 20]
    names = sorted({x for *_, x in occurrences}, key=lambda x: (len(x), x))

    def near(a, b):
        return len(names[b]) - len(names[a]) <= 2 and linededup.within(names[a], names[b], 2)

    owner = dict(zip(names, plain_components(len(names), near), strict=True))
    first, size = {}, Counter()
    for d, k, x in occurrences:
        first.setdefault(owner[x], (d, k))
        size[owner[x]] += 1
    frame = spark.createDataFrame(sorted(rows.items()), "doc_id long, text string").repartition(5)
    got = {(r.doc_id, r.line_no): r for r in linededup.classes(frame).collect()}
    assert len(got) == len(occurrences)
    for d, k, x in occurrences:
        r = got[d, k]
        assert ((r.class_doc_id, r.class_line_no), r.class_lines) == (first[owner[x]], size[owner[x]])
        assert r.kept == ((d, k) == first[owner[x]])
    found = linededup.classes(odd).collect()
    assert sum(r.kept for r in found) == 4  # one line without doc_id, the one line of both rows 6, and that of row 7
    left = {r.doc_id: r.text for r in linededup.without_repeats(frame).collect()}
    for d in rows:
        lines = [x for k, x in enumerate(rows[d].split("\n")) if (d, k) not in got or got[d, k].kept]
        assert left.get(d) == ("\n".join(lines) if lines else None)
    kept = linededup.without_repeats(odd)
    assert kept.columns == odd.columns and {r.doc_id for r in kept.collect()} >= {1, 2, 3, 4, 5, 6, 7}
    assert linededup.classes(empty).count() == 0 and linededup.without_repeats(empty).count() == 0


def test_linededup_short_lines_by_equality(spark):
    from arealex.llm import queries

    long = "a line that is long enough to be looked at"
    rows = [(1, f"And ornd.\n\n{long}\nAnd ornd."), (2, f" \t\nAnd ornd.\nAnd orne.\n{long}!"), (3, "x"), (4, "x\n" + " " * 30), (5, None)]
    got = {(r.doc_id, r.line_no): (r.class_doc_id, r.class_line_no, r.class_lines, r.kept) for r in linededup.classes(spark.createDataFrame(rows, "doc_id long, text string"), shorter=True).collect()}
    assert got == {
        (1, 0): (1, 0, 3, True), (1, 3): (1, 0, 3, False), (2, 1): (1, 0, 3, False), (2, 2): (2, 2, 1, True),
        (1, 2): (1, 2, 2, True), (2, 3): (1, 2, 2, False), (3, 0): (3, 0, 2, True), (4, 0): (3, 0, 2, False), (4, 1): (4, 1, 1, True),
    }
    texts = {r.doc_id: r.text for r in spark.read.parquet(f"{SF}/documents.parquet").collect()}
    want = {(d, k) for d, t in texts.items() for k, x in enumerate((t or "").split("\n")) if len(x) >= 20 or WORD.search(x)}
    assert {(r.doc_id, r.line_no) for r in queries.op8_line_dedup(spark, SF).collect()} == want


def test_linededup_rows_that_share_an_id(spark):
    line = "a line that an earlier document has, too, and that is long"
    rows = [(1, line), (7, f"{line}\nAnother line that is long enough"), (7, f"unique B0 in a line of its own\nunique B1 in another line\n{line}"), (None, f"{line}!\nno id, first text of those"), (None, f"no id, second text of those\n{line}?")]
    left = sorted((str(r.doc_id), r.text) for r in linededup.without_repeats(spark.createDataFrame(rows, "doc_id long, text string")).collect())
    # Of the lines that repeat one stays, of a row without doc_id; all others stay whole.
    assert [x for _, t in left for x in t.split("\n") if x.startswith("a line")] != [] and sum(x.startswith("a line") for _, t in left for x in t.split("\n")) == 1
    assert sorted(x for _, t in left for x in t.split("\n") if not x.startswith("a line")) == sorted(x for _, t in rows for x in t.split("\n") if not x.startswith("a line"))
    assert {k for k, _ in left} == {"7", "None"} and len(left) == 4


def test_linked_groups_lose_no_component(spark, monkeypatch):
    """Groups of many pieces: links within a distance on a line, against a plain version; no row is dealt to as many pieces as there are blocks when all are near."""
    monkeypatch.setattr(neardup, "REPRESENTATIVES", 2)
    rng = random.Random(8)
    rows = []
    for g, (n, spread) in enumerate(((300, 200), (300, 4000), (40, 60), (2, 1), (500, 3))):
        rows += [(g, 1000 * g + k, rng.randrange(spread)) for k in range(n)]
    frame = spark.createDataFrame(rows, "key long, id long, place long")

    def compare(g, wanted):
        return np.abs(g["place"][:, None] - g["place"][None, :]) <= 3

    from arealex.llm.common import stored
    from arealex.llm.components import connected

    got = {r.id: r.component for r in connected(neardup.linked(stored(frame), "key", ["place"], compare, 16)).collect()}
    want = plain_components(len(rows), lambda a, b: rows[a][0] == rows[b][0] and abs(rows[a][2] - rows[b][2]) <= 3)
    assert all(got.get(rows[k][1], rows[k][1]) == rows[w][1] for k, w in enumerate(want))


def test_components_of_long_chains(spark, monkeypatch):
    from arealex.llm import components

    rng = random.Random(2)
    ids = rng.sample(range(10**6), 900)
    edges = [(ids[k], ids[k + 1]) for k in range(899) if k % 300 != 299]
    rng.shuffle(edges)
    want = {i: min(ids[k // 300 * 300 : k // 300 * 300 + 300]) for k, i in enumerate(ids)}
    frame = spark.createDataFrame(edges, "u long, v long").repartition(4)
    assert {r.id: r.component for r in components.connected(frame).collect()} == want
    monkeypatch.setattr(components, "SMALL_EDGES", 10)
    assert {r.id: r.component for r in components.connected(frame).collect()} == want
    assert components.connected(frame.where("1 = 0")).count() == 0


def test_sketch_parts_are_disjoint_and_whole():
    for tau in range(16):
        bits = [b for start, size in linededup.sketch_parts(tau) for b in range(start, start + size)]
        assert bits == list(range(64)) and len(linededup.sketch_parts(tau)) == 4 * tau + 1
        assert all(size for _, size in linededup.sketch_parts(tau))


def test_long_list_finds_a_flip_in_each_byte(spark):
    rng = random.Random(12)
    signed = lambda x: x - (1 << 64) if x >> 63 else x
    rows, pairs = [], set()
    for k in range(40):
        s = rng.getrandbits(64)
        t = s
        for byte in range(8):
            t ^= 1 << 8 * byte + rng.randrange(8)
        rows += [(7, 2 * k, signed(s), 1), (7, 2 * k + 1, signed(t), 1)]
        pairs.add((2 * k, 2 * k + 1))
    posts = spark.createDataFrame(rows, "key long, id long, sketch long, hot byte")
    got = {tuple(sorted((r.u, r.v))) for r in linededup._ties(posts, 2).collect()}
    assert pairs <= got


def test_fingerprints(spark, docs, odd, empty, texts):
    order = sorted(texts, reverse=True)
    got = {r.doc_id: r for r in fingerprints.compare_neighbours(docs).collect()}
    for k, d in enumerate(order):
        t, n = texts[d], texts[order[(k + 1) % len(order)]]
        cut = len(t) // 3
        e = t[: len(t) - cut] + n[:cut]
        assert got[d].edited_sha256 == hashlib.sha256(e.encode()).hexdigest() and got[d].n_chars == len(t)
    far = [r for r in got.values() if r.n_chars > 300]
    assert np.mean([r.near_edited for r in far]) > np.mean([r.near_next for r in far]) + 0.4
    by_text = defaultdict(set)
    for d, r in got.items():
        by_text[texts[d]].add(r.fingerprint)
    assert all(len(v) == 1 for v in by_text.values())
    assert fingerprints.compare_neighbours(odd).count() == len(odd_rows()) and fingerprints.compare_neighbours(empty).count() == 0
    one = fingerprints.compare_neighbours(odd.where("doc_id = 4")).first()
    assert one.near_next == 1.0


def test_fingerprint_likeness_falls_with_edits():
    rng = random.Random(1)
    base = " ".join("".join(rng.choice("abcdefghij") for _ in range(rng.randrange(2, 9))) for _ in range(500))
    means = []
    for k in (0, 5, 40, 200):
        copies = [mutated(base, k, rng) for _ in range(5)]
        p = fingerprints.fingerprints([base, *copies])
        means.append(float(fingerprints.likeness(p[0], p[1:]).mean()))
    assert means[0] == 1.0 and means == sorted(means, reverse=True) and means[1] > 0.7 > means[3]


def test_fingerprint_classes(spark, odd, empty):
    rng = random.Random(6)
    base = [" ".join("".join(rng.choice("abcdefghij") for _ in range(rng.randrange(2, 9))) for _ in range(120)) for _ in range(6)]
    rows = [(k, mutated(base[k % 6], rng.randrange(12), rng)) for k in range(48)]
    got = {r.doc_id: r.component_id for r in fingerprints.near_classes(spark.createDataFrame(rows, "doc_id long, text string"), max_edits_percent=10).collect()}
    want = plain_components(48, lambda a, b: a % 6 == b % 6 and edits(rows[a][1], rows[b][1]) <= max(len(rows[a][1]), len(rows[b][1])) * 10 // 100)
    assert sum(got[k] == want[k] for k in range(48)) >= 46 and all(got[k] % 6 == k % 6 for k in got)
    found = [(r.doc_id, r.component_id) for r in fingerprints.near_classes(odd).collect()]
    assert len(found) == len(odd_rows()) and found.count((6, 6)) == 2 and found.count((2, 1)) == 1 and fingerprints.near_classes(empty).count() == 0


def test_fingerprint_recall(texts):
    """Pairs of texts 3 % apart or less meet in a band in at least nine of ten cases; unrelated ones don't."""
    rng = random.Random(11)
    rows = [t for t in texts.values() if t and len(t) > 300][:120]
    prints = fingerprints.fingerprints(rows)
    own = fingerprints.bands(prints)
    for percent in (1, 2, 3):
        copies = [mutated(t, max(1, len(t) * percent // 100), rng) for t in rows]
        met = (own == fingerprints.bands(fingerprints.fingerprints(copies))).any(1)
        assert met.mean() >= 0.9
    assert fingerprints.near_copies(rows[0], mutated(rows[0], len(rows[0]) * 2 // 100, rng), 3) and not fingerprints.near_copies(rows[0], rows[1], 3)


def test_walks_by_brute_force():
    """What is written against a walk of one character at a time; and Hamming distance stays small after an edit at the start."""
    rng = random.Random(2)
    text = "".join(rng.choice("abcdefghij ") for _ in range(200))
    c = np.frombuffer(text.encode("utf-32-le"), np.uint32)
    symbol = [int(fingerprints.mix64(np.array([ord(x) + 1], np.uint64))[0] >> np.uint64(56)) for x in text]
    start, length = np.array([0, 50, 120]), np.array([50, 70, 80])
    wrote = fingerprints._walks(c, start, length)
    for k in range(3):
        place, want = 0, []
        for j in range(2 * length[k]):
            seen = symbol[start[k] + place] if place < length[k] else 0
            want.append(seen)
            place += int(fingerprints._MOVES[j, seen])
        assert wrote[: 2 * length[k], k].tolist() == want
    apart = []
    for _ in range(40):
        a = "".join(rng.choice("abcdefghij ") for _ in range(240))
        b = mutated(a, 1, rng)[:240]
        both = np.frombuffer((a + b).encode("utf-32-le"), np.uint32)
        w = fingerprints._walks(both, np.array([0, 240]), np.array([240, len(b)]))
        apart.append((w[:480, 0] != w[:480, 1]).mean())
    assert np.mean(apart) < 0.15


def test_toxicity(spark, docs, odd, empty):
    sf = "/root/testdata/sf0.1"
    if not os.path.isdir(sf):
        pytest.skip("needs sf0.1")
    held = "pmod(crc32(cast(cast(doc_id as string) as binary)), 3) = 1"
    table, labels = spark.read.parquet(f"{sf}/documents.parquet"), spark.read.parquet(f"{sf}/labels.parquet")
    model = toxicity.train(table, labels.where(f"not ({held})"))
    got = toxicity.score(table.join(labels.where(held).select("doc_id", "toxic"), "doc_id").select("doc_id", "text"), model).join(labels.select("doc_id", "toxic"), "doc_id").collect()
    hits, marked = sum(r.predicted and r.toxic for r in got), sum(r.predicted for r in got)
    assert hits >= 0.45 * sum(r.toxic for r in got) and hits >= 0.9 * marked
    rows = {r.doc_id: r for r in toxicity.score(odd, model).collect()}
    assert all(0 <= r.score <= 1 for r in rows.values()) and toxicity.score(empty, model).count() == 0
    assert 0 <= toxicity.train(empty, labels).scores([""])[0] <= 1


def test_toxicity_by_brute_force(spark):
    """Sets of grams, log-count ratios and scores by plain loops."""
    from math import exp, log

    rng = random.Random(5)
    words = ["alpha", "beta", "gamma", "delta", "kind", "good"]
    texts = [" ".join(rng.choice(words) for _ in range(12)) + ("  Awful\nLoser" if k % 2 else "") for k in range(60)]
    labels = [k % 2 for k in range(60)]
    bits, m = 12, (1 << 32) - 1

    def grams(t):
        c = []
        for ch in " " + " ".join(t.lower().split()) + " ":
            x = (ord(ch) + 1) * 0x9E3779B1 & m
            c.append(x ^ x >> 15)
        out = set()
        for k in range(len(c)):
            h = c[k]
            for n in range(2, 6):
                if k + n > len(c):
                    break
                h = (h * 0x01000193 & m ^ c[k + n - 1]) * 0x85EBCA6B & m
                if n >= 3:
                    out.add(((h ^ h >> 13) * 0x9E3779B1 & m) >> 32 - bits)
        return out

    sets = toxicity.GramSets(bits)
    for t in [*texts, "", "a"]:
        assert set(sets(t).tolist()) == grams(t)
        assert set(toxicity.unpacked(toxicity.packed(sets(t), bits)).tolist()) == grams(t)
    dense = np.arange(0, 1 << bits, 2)
    assert toxicity.unpacked(toxicity.packed(dense, bits)).tolist() == dense.tolist()
    model = toxicity.fit(texts, labels, bits=bits)
    counts = [Counter(), Counter()]
    for t, y in zip(texts, labels, strict=True):
        counts[y].update(grams(t))
    for g in range(1 << bits):
        ratio = log((counts[1][g] + 1) / 32) - log((counts[0][g] + 1) / 32)
        # Weights are of the scaled features, so a bucket without a ratio has none.
        if abs(ratio) <= 0.25 or counts[0][g] + counts[1][g] < 3:
            assert model.weights[g] == 0
    frame = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    marks = spark.createDataFrame([(k, y) for k, y in enumerate(labels)], "doc_id long, toxic int")
    same = toxicity.train(frame, marks, bits=bits)
    for r in toxicity.score(frame, same).collect():
        want = 1 / (1 + exp(-(sum(float(same.weights[g]) for g in grams(texts[r.doc_id])) + same.bias)))
        assert abs(r.score - want) < 1e-5 and r.predicted == labels[r.doc_id]


PAGE = """<!DOCTYPE html><html><body><header>Site</header><div id="menu-main"><a href=x>Home</a></div><div class="wrap"><div class="post-body">
<h2>Title {k}</h2><p>Some &lt;long&gt; text, number {k}<br>with   words {w}.<div class="share">Share this</div><div class="note">Constant note</div>
<ul><li>one<li>two {k}</ul></div><aside>side {k}</aside></div><div class="comments"><p>nice {k}</p></div><form>f</form><footer>f {k}</footer><script>var x="</p>";</script></body></html>"""


def test_extraction(spark):
    pages = [PAGE.format(k=k, w=" ".join([f"w{k}"] * 30)) for k in range(5)]
    rows = [(k, f"http://a.example.org/{k}", p) for k, p in enumerate(pages)] + [(7, None, None), (8, "http://b.example.org", ""), (9, "http://b.example.org", "just <b>text</b>"), (9, "http://b.example.org", "just <b>text</b>")]
    frame = spark.createDataFrame(rows, "page_id long, url string, html string")
    got = {r.page_id: r for r in extraction.extract_pages(frame).collect()}
    for k in range(5):
        want = f"Title {k}\n\nSome <long> text, number {k} with words {' '.join([f'w{k}'] * 30)}.\n\none\n\ntwo {k}"
        assert got[k].text == want and got[k].n_chars == len(want)
    assert got[7].text == "" and got[8].text == "" and got[9].text == "just text"
    assert extraction.extract_pages(frame).count() == len(rows)
    assert extraction.extract_pages(frame.where("1 = 0")).count() == 0


def test_extraction_on_pages(spark):
    import html

    for r in extraction.extract_pages(spark.read.parquet(f"{SF}/pages.parquet")).join(spark.read.parquet(f"{SF}/pages.parquet").select("page_id", "html"), "page_id").collect():
        inner = r.html[r.html.index("<article>") + 9 : r.html.index("</article>")]
        parts = [" ".join(html.unescape(re.sub(r"<[^>]+>", " " if "br" in x else "", x)).split()) for x in re.split(r"</?(?:p|h1)>", inner.replace("<br>", " "))]
        assert r.text == "\n\n".join(filter(None, parts))


def _extracted(spark, rows, schema="page_id long, url string, html string"):
    return {r.page_id: r.text for r in extraction.extract_pages(spark.createDataFrame(rows, schema)).collect()}


def test_extraction_keeps_articles_over_several_parts(spark):
    words = lambda k, n: " ".join(f"w{k}x{j}" for j in range(n))
    page = "<html><body><div class='top'>The site</div><div id=a1><p>{a}</p></div><div id=b2><p>{b}</p></div><div>ab <b>much {k} longer text than before</b> end</div><div class='cookie-notice'>Cookies {k}</div></body></html>"
    rows = [(k, "http://h.example.org/x", page.format(k=k, a=words(k, 130), b=words(k + 50, 60))) for k in range(6)]
    got = _extracted(spark, rows)
    for k in range(6):
        assert got[k] == f"{words(k, 130)}\n\n{words(k + 50, 60)}\n\nab much {k} longer text than before end"
    # A class name that also says something else doesn't decide; nor do names where the page is the only one of its host.
    table = "<main><h1>Prices</h1><div class='share-price table'>Eleven up, {k} down</div><p>And {k} on.</p></main>"
    got = _extracted(spark, [(k, f"http://p{k % 2}.example.org", table.format(k=k)) for k in range(3)])
    assert got == {k: f"Prices\n\nEleven up, {k} down\n\nAnd {k} on." for k in range(3)}


def test_extraction_learns_from_all_pages_of_a_host(spark):
    """Of 300 pages a few have a notice, whose class says nothing; and one layout is rare. Constant text is template wherever it is, in any split of the table."""
    rows = []
    for k in range(300):
        notice = "<div class=x9>We are moving house in May</div>" if k % 50 == 7 else ""
        teaser = "<section>See also the other site</section>" if k >= 290 else ""
        rows.append((k, "https://hot.example.org/a", f"<html><body><div>Masthead</div>{notice}<div><h2>T {k}</h2><p>text of page {k} and more</p></div>{teaser}<div>All rights with us</div></body></html>"))
    frame = spark.createDataFrame(rows, "page_id long, url string, html string")
    for parts in (1, 7):
        got = {r.page_id: r.text for r in extraction.extract_pages(frame.repartition(parts)).collect()}
        assert got == {k: f"T {k}\n\ntext of page {k} and more" for k in range(300)}


def test_extraction_of_a_page_does_not_hang_on_how_many_others_there_are(spark):
    """A constant text of two pages is template beside three other pages and beside many, whose odd elements would make a wrapper of thousands of units."""
    word = lambda n: "q" + "".join(chr(97 + int(d)) for d in str(n))

    def page(k, notice):
        odd = "".join(f"<div class={word(1000 * k + j)}>Part {word(7 * k + j)} of page {k} says {j}</div>" for j in range(30))
        return f"<html><body><div class=qmain>{odd}</div>{notice and '<div class=zline>Printed in the north</div>'}<div class=qend>Page number {k}</div></body></html>"

    def texts(n):
        rows = [(k, "http://one.example/", page(k, k in (1, 2))) for k in range(n)]
        found = extraction.extract_pages(spark.createDataFrame(rows, "page_id long, url string, html string").repartition(3)).where("page_id < 5").collect()
        return {r.page_id: r.text for r in found}

    few, many = texts(5), texts(130)
    assert few == many and all("Printed" not in t and t.count("says") == 30 for t in few.values())
    w = extraction.wrappers(spark.createDataFrame([(k, "http://one.example/", page(k, False)) for k in range(130)], "page_id long, url string, html string")).first()
    assert len(json.loads(json.loads(w.wrappers)["html>body"])[1]) < 10


def test_extraction_of_copies_and_single_pages(spark):
    page = "<html><body><div>One text</div><p>that all copies have</p></body></html>"
    got = _extracted(spark, [(k, "http://c.example.org", page) for k in range(5)] + [(9, "http://one.example.org", page), (10, None, page)])
    assert set(got.values()) == {"One text\n\nthat all copies have"}


def test_extraction_of_deep_long_and_odd_pages(spark):
    import time

    n = 5000
    deep = "<div>" * n + "deep text" + "</div>" * n
    spans = "<p>" + "<span>" * n + "inline text" + "</span>" * n + "</p>"
    listy = "<ul>" + "<li><a href=x>link</a></li>" * 5 + "</ul><p>kept</p>"
    long = lambda k: "<html><body><div>Same</div>" + "".join(f"<h2>h {j} {k if j % 3 else 'x'}</h2><p>text {j} {k}</p><div class=c{'abc'[(j + k) % 3]}>d {j} {k}</div>" for j in range(5000)) + "</body></html>"
    rows = [(1, "http://d.example.org", deep), (2, "http://d.example.org", deep.replace("deep", "other deep")), (3, "http://s.example.org", spans), (4, "http://s.example.org", listy), (5, "x", "<" * 2000), (6, "x", "<p>a &amp; b &lt;c&gt; <br> d</p><p></p>  e"), (7, None, None), (8, "", "")]
    rows += [(100 + k, "http://long.example.org", long(k)) for k in range(4)]
    began = time.time()
    frame = spark.createDataFrame([(*r, 1, 2, 3) for r in rows], "page_id long, url string, html string, host int, text int, wrappers int")
    got = {r.page_id: r.text for r in extraction.extract_pages(frame).collect()}
    assert time.time() - began < 90
    assert got[1] == "deep text" and got[2] == "other deep text" and got[3] == "inline text" and got[4] == "kept" and got[6] == "a & b <c> d\n\ne" and got[7] == got[8] == ""
    for k in range(4):
        assert len(rows[-1][2]) > 200_000 and got[100 + k].count("\n\n") >= 3 * 5000 - 2 - 1700 and not got[100 + k].startswith("Same")
        assert all(f"text {j} {k}" in got[100 + k] for j in range(0, 5000, 499))


def test_tree_matching_by_brute_force(monkeypatch):
    """The size of the best matching against all order-keeping matchings, by plain recursion; and the pairing adds up to it."""
    rng = random.Random(4)

    def tree(depth):
        u = extraction.Unit(rng.choice("abc"), rng.choice(["1", "2", None]), 1, [tree(depth - 1) for _ in range(rng.randrange(4))] if depth else [])
        extraction._shaped(u)
        return u

    def plain(a, b):
        if a.sig != b.sig:
            return 0

        def best(x, y):
            if not x or not y:
                return 0
            return max(best(x[1:], y), best(x, y[1:]), plain(x[0], y[0]) + best(x[1:], y[1:]))

        return 1 + best(a.kids, b.kids)

    for _ in range(300):
        a, b = tree(3), tree(3)
        assert extraction.matched(a, b, {}) == plain(a, b)
        size, pairs = extraction.aligned(a.kids, b.kids, {})
        assert size == sum(plain(a.kids[i], b.kids[j]) for i, j in pairs) and pairs == sorted(pairs) and len({j for _, j in pairs}) == len(pairs)
        back = extraction.unflat(extraction.flat(a))
        assert extraction.flat(back) == extraction.flat(a) and back.shape == a.shape
        monkeypatch.setattr(extraction, "CELLS", 0)
        size, pairs = extraction.aligned(a.kids, b.kids, {})
        assert pairs == sorted(pairs) and len({j for _, j in pairs}) == len(pairs) and all(a.kids[i].sig == b.kids[j].sig for i, j in pairs)
        monkeypatch.setattr(extraction, "CELLS", 40_000)


def test_long_sibling_lists_are_matched_whole():
    """250 by 250 units, of which some occur once out of order and others lie far apart: as large a matching as the full table's, and the same pairs."""
    rng = random.Random(9)

    def listed(order):
        out = []
        for k in order:
            out.append(extraction.Unit(f"s{k % 4}", None, 1, [extraction.Unit(f"k{j}", None, 1, []) for j in range(k % 7)]))
            if k % 50 == 0:
                out.append(extraction.Unit("once", None, 1, [extraction.Unit(f"o{k}", None, 1, [])]))
        for u in out:
            for v in u.kids:
                extraction._shaped(v)
            extraction._shaped(u)
        return out

    def whole(x, y):
        best = [[0] * (len(y) + 1) for _ in range(len(x) + 1)]
        for i, u in enumerate(x):
            for j, v in enumerate(y):
                best[i + 1][j + 1] = max(best[i][j + 1], best[i + 1][j], best[i][j] + extraction.matched(u, v, {}))
        return best[-1][-1]

    for back in (False, True):
        x, y = list(range(250)), list(range(250))
        rng.shuffle(x)
        rng.shuffle(y)
        if back:
            x, y = x[:5] + sorted(x[5:]), sorted(y[:120]) + y[120:]
        x, y = listed(x), listed(y)
        size, pairs = extraction.aligned(x, y, {})
        assert size == whole(x, y) == sum(extraction.matched(x[i], y[j], {}) for i, j in pairs)
        assert extraction._rows(x, y, {}, True) == extraction._table(x, y, {}, True)
    # Units far beyond the place of their like are paired, too.
    x, y = listed([1] * 200 + [2, 2, 1]), listed([3] * 400 + [2, 2, 3])
    assert [p for p in extraction.aligned(x, y, {})[1] if p[0] in (200, 201)] == [(200, 400), (201, 401)]
