"""The registered queries on a small odd corpus: null keys and columns, empty and very long texts, ties, repeated rows and
columns whose names clash with those that operators add. Each query is held against its own brute-force version."""

import functools
import hashlib
import math
import random
import zlib
from collections import Counter

import numpy as np
import pytest

from cutline.llm import html_text, language, mixing, near_dup, packing, registry, toxicity
from cutline.llm.ngrams import FOLD

from test_operators import brute_best_fit, brute_components, brute_lines, brute_sets, brute_targets, words

CLASH = ["score", "shard", "row", "rank", "part", "slot", "kept", "size", "copies", "label", "n", "owner", "first", "group0", "size_", "page", "host", "predicted", "lang_pred", "n_lines", "token", "component_id"]
rng = random.Random(23)


@functools.lru_cache(maxsize=1)
def corpus():
    base, common = words(80), "one and the same line of many words"
    texts = [None, "", " \t\n ", "\n\n", "7 % 7", "word", base, base, base, f"{common}\n{words(9)}", *(f"{common.upper()} \n{words(12)}\n\nend" for _ in range(11)), *([base + " " + base[:40]] * 12)]
    texts += [" ".join(words(2) for _ in range(30_000)), "x" * 120_000, "漢字かな交じり文 " * 900, "Straße über zoë naïve " * 3]
    texts += [f"{words(40)} {rng.choice(['awful', 'nasty'])}word" if i % 3 == 0 else words(40) for i in range(90)]
    langs, sources = ["en", "de", None, "fr"], [None, "a", "b", "B", "zz", "a", "a"]
    rows = [(i, t, langs[i % 4], sources[i % 7]) for i, t in enumerate(texts)]
    return [*rows, rows[6], rows[6], (None, "a text without a key of its own", "en", "a"), (None, None, None, None), (3, "another text of a key", "en", "b")]


@pytest.fixture(scope="module")
def odd(spark, tmp_path_factory):
    from pyspark.sql import functions as F

    folder = str(tmp_path_factory.mktemp("odd"))
    write = lambda df, name: df.select("*", *[F.lit("clash").alias(c) for c in CLASH if c not in df.columns]).write.parquet(f"{folder}/{name}.parquet")
    docs = corpus()
    write(spark.createDataFrame([(*r, len(r[1] or "")) for r in docs], "doc_id long, text string, lang string, source string, n_chars long").repartition(3), "documents")
    write(spark.createDataFrame([(k, 1, int("awful" in (t or "") or "nasty" in (t or ""))) for k, t, *_ in docs] + [(None, 1, 1), (5, 1, None), (99999, 0, 1)], "doc_id long, quality int, toxic int"), "labels")
    r = np.random.default_rng(5)
    vectors = [(i, [float(x) for x in v]) for i, v in enumerate(r.normal(size=(260, 8)).astype(np.float32))]
    vectors += [(500, None), (501, [1.0, None]), (502, [float("inf")] * 8), (None, vectors[0][1]), vectors[7], vectors[100], (503, []), (600, [0.0] * 8)]
    write(spark.createDataFrame(vectors, "vec_id long, embedding array<float>"), "embeddings")
    pages = [(i, f"http://H{i % 2}.example/p", f"<body><div class=q7>Same on all pages</div><p>{words(9)}</p></body>") for i in range(10)]
    pages += [(10, None, None), (11, "x", ""), (None, "http://h0.example", f"<p>{words(5)}</p>"), pages[0], (12, "http://long", "<div><p>" + "long " * 60_000 + "<b>end"), (13, "http://deep", "<div>" * 3000 + "deep")]
    write(spark.createDataFrame(pages, "page_id long, url string, html string"), "pages")
    return folder


@pytest.fixture(scope="module")
def none(spark, odd, tmp_path_factory):
    folder = str(tmp_path_factory.mktemp("none"))
    for name in ("documents", "labels", "embeddings", "pages"):
        spark.read.parquet(f"{odd}/{name}.parquet").limit(0).write.parquet(f"{folder}/{name}.parquet")
    return folder


def run(spark, folder, name):
    (found,) = (f for k, f in registry.queries().items() if k.split("_")[0] == name)
    return found(spark, folder).collect()


def crc(k, n):
    return k is not None and zlib.crc32(str(k).encode()) % n


@pytest.mark.parametrize("name", [f"op{i}" for i in range(1, 11)])
def test_empty_tables(spark, none, name):
    assert run(spark, none, name) == []


def test_op1(spark, odd):
    whole = [(r.vec_id, r.embedding) for r in spark.read.parquet(f"{odd}/embeddings.parquet").collect()]
    sound = [(i, [math.floor(1024 * x) for x in v]) for i, v in whole if i is not None and v is not None and all(x is not None and math.isfinite(x) for x in v)]
    want = []
    by = Counter(i for i, _ in sound)
    for q in sorted({i for i, _ in sound if i % 100 == 0}):
        v = next(v for i, v in sound if i == q)
        scores = sorted((-sum(a * b for a, b in zip(v, w, strict=False)), i) for i, w in sound if i != q for _ in range(by[q]))[:10]
        want += [(q, n + 1, i, -s) for n, (s, i) in enumerate(scores)]
    assert sorted(tuple(r) for r in run(spark, odd, "op1")) == want


def test_op2(spark, odd):
    def owner(k, n):
        key = "n" if k is None else f"k{k}"
        return min((-math.log((int(hashlib.md5(f"{key}:{s}".encode()).hexdigest()[:12], 16) + 0.5) / 2**48), s) for s in range(n))[1]

    rows = run(spark, odd, "op2")
    want = Counter((k, len((t or "").encode()) + 8, zlib.crc32((t or "").encode()), "key", owner(k, 24), owner(k, 25)) for k, t, *_ in corpus())
    assert Counter((r.doc_id, r.size, r.text_crc32, r.law, r.shard, r.grown_shard) for r in rows) == want
    for s in range(24):
        assert sorted(r.slot for r in rows if r.shard == s) == list(range(sum(r.shard == s for r in rows)))


def test_op3(spark, odd):
    docs = corpus()
    count = lambda t: len([w for w in "".join(" " if c in "\t\n\x0b\x0c\r" else c for c in t or "").split(" ") if w])
    sizes = Counter()
    for _, t, _, s in docs:
        sizes[s] += count(t)
    want = brute_targets(sizes, [5, 2, 1], 1.5, 2)
    rows = run(spark, odd, "op3")
    longest = {s: max(count(t) for _, t, _, o in docs if o == s) for s in sizes}
    of = {v: s for s, v in sizes.items()}
    assert len(of) == len(sizes)
    assert Counter((r.doc_id, r["size"], r.source_size) for r in rows) == Counter((k, count(t), sizes[s]) for k, t, _, s in docs)
    taken = Counter()
    for r in rows:
        assert abs(r.target - want[of[r.source_size]]) < 1e-6 and (r["size"] == 0 or r.taken / r["size"] in (0, 1, 2))
        taken[of[r.source_size]] += r.taken
    assert all(abs(taken[s] - want[s]) <= longest[s] for s in sizes)
    assert Counter(map(str, run(spark, odd, "op3"))) == Counter(map(str, rows))


def test_multipliers_solve_the_dual(spark):
    """Bisection, source by source, gives the same multipliers; copies follow the rates in every running total."""
    cells = [(f"s{i}", size, rng.randint(1, 30)) for i in range(40) for size in rng.sample(range(1, 200), 12)] + [(None, 10, 3)]
    df = spark.createDataFrame(cells, "source string, size long, n long")
    targets = mixing.source_targets(df, [5.0, 2.0, 1.0], 1.5, 2.0)
    want = {r.source: r.target for r in targets.collect()}
    got = {r.source: (r.multiplier, r.mean) for r in mixing.balance(df, targets, 2.0).collect()}
    rate = lambda z: 2 * math.exp(z) / (1 + math.exp(z))
    for s, (x, mean) in got.items():
        own = [(size, n) for o, size, n in cells if o == s]
        total = sum(size * n for size, n in own)
        if want[s] >= 2 * total * (1 - 1e-12):
            assert x == mixing.BOUND
            continue
        low, high = -60.0, 60.0
        for _ in range(100):
            mid = (low + high) / 2
            low, high = (mid, high) if sum(n * size * rate(mid * size / mean) for size, n in own) < want[s] else (low, mid)
        assert abs(x - low) < 1e-4
        words_at = sum(n * size * rate(x * size / mean) for size, n in own)
        assert abs(words_at - want[s]) <= 1e-6 * want[s]
    copies = {(r.source, r["size"]): r.copies for r in mixing.copies_per_cell(df, targets, mixing.balance(df, targets, 2.0), 2).collect()}
    for s in got:
        own = [(size, n) for o, size, n in cells if o == s]
        assert all(0 <= copies[s, size] <= 2 * n for size, n in own)
        assert abs(sum(copies[s, size] * size for size, _ in own) - want[s]) <= max(1, max(size for size, _ in own))


def test_op4(spark, odd):
    docs = corpus()
    want = Counter()
    for (k, *_), (n, kept), t in zip(docs, brute_lines([d[1] for d in docs], 10), [d[1] for d in docs], strict=True):
        lines = (t or "").split("\n")
        key = lambda x: x.strip(" \t\n\x0b\x0c\r").lower()
        gone = n - (len(kept.split("\n")) if kept or any(not key(x) for x in lines) else 0)
        want[k, n, gone, hashlib.sha256(kept.encode()).hexdigest()] += 1
    assert Counter((r.doc_id, r.n_lines, r.n_dropped, r.kept_sha256) for r in run(spark, odd, "op4")) == want


def test_op5(spark, odd):
    from tokenizers import Tokenizer

    slow = Tokenizer.from_file(packing.default_vocabulary())
    want, lengths = Counter(), []
    for k, t, *_ in corpus():
        ids = np.array([*slow.encode(t or "", add_special_tokens=False).ids, 1], "<u4")
        for at in range(0, len(ids), 2048):
            piece = ids[at : at + 2048]
            lengths.append(len(piece))
            want[k, at, len(piece), zlib.crc32(piece.tobytes()), len(ids)] += 1
    rows = run(spark, odd, "op5")
    assert Counter((r.doc_id, r.start, r.length, r.ids_crc32, r.doc_tokens) for r in rows) == want
    by = {}
    for r in rows:
        by.setdefault(r.sequence_id, []).append((r.offset, r.length))
    for own in by.values():
        own.sort()
        assert own[0][0] == 0 and all(a + n == b for (a, n), (b, _) in zip(own, own[1:], strict=False))
    assert sorted(sum(n for _, n in own) for own in by.values()) == brute_best_fit(lengths, 2048)


def test_encoders_agree(monkeypatch):
    import builtins

    r = random.Random(9)
    quick = packing.encoder(packing.default_vocabulary())
    real = builtins.__import__
    monkeypatch.setattr(builtins, "__import__", lambda name, *a, **k: (_ for _ in ()).throw(ImportError(name)) if name == "tiktoken" else real(name, *a, **k))
    plain = packing.encoder.__wrapped__(packing.default_vocabulary())
    for _ in range(400):
        t = "".join(r.choice("ab  \t\n\r'sll re.,;0129äß漢ñ😀‍́\xa0ⅷ٣") for _ in range(r.randint(0, 60)))
        assert quick(t).tolist() == plain(t).tolist()


def test_op6(spark, odd):
    rows = run(spark, odd, "op6")
    want = Counter()
    for k, t, *_ in corpus():
        raw = (t or "").encode()
        payload = raw + b"\0" * (-len(raw) % 64 if raw else 64)
        want[k, len(raw), len(payload), hashlib.sha256(payload).hexdigest(), zlib.crc32(payload[-64:])] += 1
    assert Counter((r.doc_id, r.n_bytes, r.payload_bytes, r.payload_sha256, r.tail_crc32) for r in rows) == want
    same = {}
    for r in rows:
        assert same.setdefault(r.payload_sha256 + str(r.n_bytes), (r.media_bytes, r.media_sha256, r.feature)) == (r.media_bytes, r.media_sha256, r.feature)
    assert len({r.feature for r in rows}) > 20


def test_op7(spark, odd):
    pages = spark.read.parquet(f"{odd}/pages.parquet").collect()
    rows = run(spark, odd, "op7")
    low = {"h0.example": {"/body/div.q0"}, "h1.example": {"/body/div.q0"}}
    want = Counter((p.page_id, p.url, html_text.main_text(p.html, frozenset(low.get(html_text.host_of(p.url), ())))) for p in pages)
    assert Counter((r.page_id, r.url, r.text) for r in rows) == want
    assert all(r.n_chars == len(r.text) and "Same on" not in r.text for r in rows) and sum(r.text.startswith("long long") for r in rows) == 1


def grams(text, orders):
    """Each n-gram of a folded text as bytes, with its order."""
    raw = b" " + bytes(int(FOLD[b]) for b in (text or "").lower().encode()) + b" "
    return [(n, raw[i : i + n]) for n in orders for i in range(len(raw) - n + 1)]


def hashed(n, raw):
    from cutline.llm.ngrams import rolling

    return int(rolling(np.frombuffer(raw, np.uint8), n)[0])


def test_op8(spark, odd):
    docs = corpus()
    rows = run(spark, odd, "op8")
    assert Counter((r.doc_id, r.held_out) for r in rows) == Counter((k, k is not None and crc(k, 5) == 0) for k, *_ in docs)
    assert all(0 <= r.score <= 1 and r.predicted == int(r.score >= 0.5) for r in rows)
    # counts, features and scores from the definition, n-gram by n-gram
    labelled = [(i, t, int("awful" in (t or "") or "nasty" in (t or ""))) for i, (_, t, *_) in enumerate(docs) if len(t or "") < 5000]
    df = spark.createDataFrame(labelled, "key long, text string, label int")
    slots = {i: {hashed(n, g) % toxicity.SLOTS for n, g in grams(t, toxicity.ORDERS)} for i, t, _ in labelled}
    clean, toxic, n0, n1 = toxicity.count_features(df)
    for label, got in ((0, clean), (1, toxic)):
        want = Counter(s for i, _, y in labelled if y == label for s in slots[i])
        assert {s: int(got[s]) for s in np.flatnonzero(got).tolist()} == dict(want)
    assert (n0, n1) == tuple(sum(y == v for *_, y in labelled) for v in (0, 1))
    model = toxicity.train(df, len(labelled))
    for r in toxicity.predict(df, model).collect():
        z = model.bias + sum(float(model.weights[s]) for s in slots[r.key])
        assert abs(r.score - 1 / (1 + math.exp(-z))) < 1e-5
        assert r.predicted == r.label


def test_op9(spark, odd):
    docs = corpus()
    own = brute_sets([t for _, t, *_ in docs])
    # texts are classed by rows, then each row has the smallest id of its class, null before all
    rows = list(range(len(docs)))
    comp = brute_components(rows, own)
    least = {}
    for i in rows:
        k = docs[i][0]
        least.setdefault(comp[i], []).append(k)
    found = Counter((r.doc_id, r.n_shingles, r.component_id) for r in run(spark, odd, "op9"))
    want = Counter((docs[i][0], len(own[i]), min((k for k in least[comp[i]] if k is not None), default=None)) for i in rows)
    assert found == want


def test_links_are_all_found(spark, odd):
    docs = [(i, t) for i, (_, t, *_) in enumerate(corpus())]
    family = words(90).split()
    for i in range(60):
        t = list(family)
        for _ in range(rng.randint(0, 6)):
            t[rng.randrange(90)] = f"z{rng.randrange(999)}"
        docs.append((1000 + i, " ".join(t)))
    own = brute_sets([t for _, t in docs])
    want = {i: sum(bool(s) and bool(t) and i != j and 100 * len(s & t) >= 75 * len(s | t) for (j, _), t in zip(docs, own, strict=True)) for (i, _), s in zip(docs, own, strict=True)}
    df = spark.createDataFrame(docs, "doc_id long, text string").repartition(5)
    assert {r.doc_id: r.n_links for r in near_dup.link_counts(df).collect()} == want


def test_piles_lose_no_links(spark, monkeypatch):
    """Lists far longer than a pile: each family is one component, and lists that two families share don't join them."""
    monkeypatch.setattr(near_dup, "PILE", 8)
    common = words(60)
    rows = [(1000 * f + i, f"{common} {' '.join(f'f{f}x{j}' for j in range(16))} e{f}y{i}") for f in range(3) for i in range(70)]
    own = brute_sets([t for _, t in rows])
    want = brute_components([i for i, _ in rows], own)
    got = near_dup.near_duplicates(spark.createDataFrame(rows, "doc_id long, text string").repartition(4))
    assert {r.doc_id: r.component_id for r in got.collect()} == want


def test_prefixes_follow_the_cost(spark):
    """Sets whose shingles stand alone need one match; sets in long lists are held to more."""
    many = [(i, f"{words(300)} {i}") for i in range(40)]
    body = " ".join(f"c{j}" for j in range(200))
    copies = [(100 + i, f"{body} v{i} w{i}") for i in range(12)]
    df = spark.createDataFrame(many + copies, "doc_id long, text string")
    _, known = near_dup.describe_docs(df, "doc_id", "text")
    import pyarrow as pa

    from cutline.llm.shingles import sets

    matches = [near_dup.prefix(s, known)[2] for s in sets(pa.array([t for _, t in many + copies]))]
    assert set(matches[:40]) == {1} and set(matches[40:]) == {near_dup.MOST_MATCHES}


def test_op10(spark, odd):
    docs = corpus()
    rows = run(spark, odd, "op10")
    assert Counter((r.doc_id, r.held_out) for r in rows) == Counter((k, k is not None and crc(k, 3) == 1) for k, *_ in docs)
    letter = lambda t: any(c.isalpha() for c in t or "")
    assert {r.lang_pred for r in rows} <= {"en", "de", "fr", "und"} and sum(r.lang_pred == "und" for r in rows) == sum(not letter(t) for _, t, *_ in docs)
    short = [(k, t, lang) for k, t, lang, _ in docs if len(t or "") < 5000]
    filters = language.train(spark.createDataFrame(short, "doc_id long, text string, lang string"))
    # the filter's contents, from the definition
    counts, total = Counter(), Counter()
    for _, t, lang in short:
        if lang and t is not None:
            for n, g in grams(t, language.ORDERS):
                counts[lang, n, g] += 1
    repeated = {x: c for x, c in counts.items() if c >= 2}
    for (lang, n, _), c in repeated.items():
        total[lang, n] += c
    best = {}
    for (lang, n, g), c in repeated.items():
        best[n, g] = max(best.get((n, g), 0), c / total[lang, n])
    masks = {}
    for (lang, n, g), c in repeated.items():
        if c / total[lang, n] >= 0.35 * best[n, g]:
            h = hashed(n, g)
            masks[h] = masks.get(h, 0) | 1 << filters.langs.index(lang)
    (part,) = filters.filters
    want = np.zeros(part.slots, np.int64)
    for h, m in masks.items():
        for at in (h & (part.slots - 1), (h >> language.PROBE_SHIFT) & (part.slots - 1)):
            want[at] |= m
    assert part.masks.tolist() == want.tolist()
    # the decision, popcount by popcount
    false = [(sum(m >> i & 1 for m in want.tolist()) / part.slots) ** 2 for i in range(3)]
    tried = [(k, t, lang) for k, t, lang in short if letter(t)]
    for r in language.predict(spark.createDataFrame(tried, "doc_id long, text string, lang string"), filters).collect():
        score = [0.0] * 3
        for n in language.ORDERS:
            found = [int(want[h & (part.slots - 1)] & want[(h >> language.PROBE_SHIFT) & (part.slots - 1)]) for h in (hashed(n, g) for m, g in grams(r.text, (n,)) if m == n)]
            for i in range(3):
                score[i] += n * max(0.0, sum(m >> i & 1 for m in found) - len(found) * false[i]) / (1 - false[i])
        assert abs(r.score - max(score) / max(sum(score), 1e-12)) < 1e-6
        assert abs(score[filters.langs.index(r.lang_pred)] - max(score)) < 1e-9


def test_pipeline_by_stages(spark, odd, none):
    """Each stage on its own input against a brute-force version; rows that share a doc_id are rows of their own."""
    import corpus_pipeline as pipe
    from cutline.llm.common import stored

    docs = spark.read.parquet(f"{odd}/documents.parquet")
    stages = dict(pipe.STAGES)
    rows = lambda df: [(r.doc_id, r.text, r.lang, r.source) for r in df.collect()]
    first = stored(stages["language_id"](spark, docs, odd), "test")
    kept = [d for d in corpus() if any(c.isalpha() for c in d[1] or "")]
    assert Counter((k, t, s) for k, t, _, s in rows(first)) == Counter((k, t, s) for k, t, _, s in kept)
    second = stored(stages["line_dedup"](spark, first, odd), "test")
    got = rows(second)
    frequent = Counter(x for _, t, *_ in kept for x in {y.strip(" \t\n\x0b\x0c\r").lower() for y in t.split("\n")})
    often = {x for x, n in frequent.items() if x and n >= 10}
    left = Counter(y.strip(" \t\n\x0b\x0c\r").lower() for _, t, *_ in got for y in t.split("\n"))
    assert len(got) == len(kept) and all(left[x] == 1 for x in often)
    strip = lambda t: "\n".join(y for y in t.split("\n") if y.strip(" \t\n\x0b\x0c\r").lower() not in often)
    assert Counter((k, strip(t)) for k, t, *_ in got) == Counter((k, strip(t)) for k, t, *_ in kept)
    third = stored(stages["near_duplicates"](spark, second, odd), "test")
    own = brute_sets([t for _, t, *_ in got])
    comp = brute_components(list(range(len(got))), own)
    classes = {}
    for i, c in comp.items():
        # equal rows count once, so a text without words is a class by its row
        classes.setdefault(c if own[i] else ("row", str(got[i])), []).append((got[i][0] is not None, got[i][0] or 0))
    assert sorted((r.doc_id is not None, r.doc_id or 0) for r in third.collect()) == sorted(min(v) for v in classes.values())
    fourth = stored(stages["mixing"](spark, third, odd), "test")
    copies = Counter(rows(fourth))
    size = lambda t: len((t or "").split())
    sizes = Counter()
    for k, t, lang, s in rows(third):
        sizes[s] += size(t)
        assert copies[k, t, lang, s] <= 2
    want, taken = brute_targets(sizes, [5, 2, 1], 1.5, 2), Counter()
    for (_, t, _, s), n in copies.items():
        taken[s] += n * size(t)
    assert set(copies) <= set(rows(third)) and all(abs(taken[s] - want[s]) <= max(size(t) for _, t, _, o in rows(third) if o == s) for s in sizes)
    last = stages["packing"](spark, fourth, odd).collect()
    assert Counter(r.doc_id for r in last if r.start == 0) == Counter(r.doc_id for r in fourth.collect())
    assert pipe.run(spark, none).count() == 0


def test_pipeline_goes_on_and_cleans_up(spark, odd, tmp_path, monkeypatch):
    """A run that fails in a stage leaves the stages before it, which the next run takes up; intermediate tables go with their stage."""
    import os

    import corpus_pipeline as pipe
    from cutline.llm import common

    calls = []
    plain = {"language_id": lambda s, d, f: common.stored(d.limit(30), "some").select("doc_id", "text"), "line_dedup": lambda s, d, f: d.filter("doc_id is not null")}

    def step(name):
        def run(s, docs, sf_dir):
            calls.append(name)
            if name == "line_dedup" and calls.count(name) == 1:
                raise RuntimeError("lost")
            return plain[name](s, docs, sf_dir)

        return run

    monkeypatch.setattr(pipe, "STAGES", [("language_id", step("language_id")), ("line_dedup", step("line_dedup")), ("packing", lambda s, d, f: d)])
    before = len(common._made)
    with pytest.raises(RuntimeError):
        pipe.run(spark, odd, str(tmp_path))
    done = pipe.run(spark, odd, str(tmp_path))
    assert calls == ["language_id", "line_dedup", "line_dedup"] and done.filter("doc_id is null").count() == 0
    assert len(common._made) == before and sorted(os.listdir(tmp_path)) == ["0-language_id", "1-line_dedup"]
