"""The corpus operators against brute force, round trips and held-out accuracy, and on broken input."""

import hashlib
import random
import zlib
from collections import Counter

import numpy as np
import pytest

from cutline.llm import avi, html_text, language, line_dedup, mixing, near_dup, packing, sharding, shingles, topk, toxicity

SCHEMA = "doc_id long, text string, lang string, source string, n_chars long, score string, kept string, row string, shard string"
rng = random.Random(7)
VOCABULARY = [f"w{i}" for i in range(300)]


def words(n):
    return " ".join(rng.choice(VOCABULARY) for _ in range(n))


@pytest.fixture(scope="module")
def texts():
    base = words(60)
    t = base.split()
    near = [" ".join([*t[:i], "x%d" % i, *t[i + 1 :]]) for i in (3, 30, 31, 58)]
    far = [" ".join("y%d" % i if i % 9 == 0 else x for i, x in enumerate(t))]
    return [None, "", " \t\n", "one", "two words", base, base, base.upper(), *near, *far, "shared line\n" + words(20), *(f" Shared LINE \n{words(8)}" for _ in range(11)), words(3000), "zoë 漢字\n\n" + words(5)]


@pytest.fixture(scope="module")
def docs(spark, texts):
    rows = [(i, t, "en" if i % 2 else None, None if i % 5 == 0 else f"s{i % 3}", 1, "a", "b", "c", "d") for i, t in enumerate(texts)]
    return spark.createDataFrame([*rows, rows[-1]], SCHEMA)  # the last row stands twice


@pytest.fixture(scope="module")
def empty(spark):
    return spark.createDataFrame([], SCHEMA)


# 1 ----------------------------------------------------------------------------------------------------


def brute_top(rows, k):
    out = []
    for q, v in rows:
        if q % 100 == 0:
            best = sorted(((-sum(a * b for a, b in zip(v, w, strict=False)), i) for i, w in rows if i != q))[:k]
            out += [(q, r + 1, i, -s) for r, (s, i) in enumerate(best)]
    return sorted(out)


@pytest.mark.parametrize("kind", ["random", "ties", "negative"])
def test_topk_is_exact(spark, kind):
    r = np.random.default_rng(3)
    data = r.normal(size=(600, 12)) if kind == "random" else np.repeat(r.normal(size=(3, 12)), 200, 0) if kind == "ties" else -np.abs(r.normal(size=(400, 12)))
    rows = [(i, [float(np.float32(x)) for x in v]) for i, v in enumerate(data)]
    bad = [(1000, None), (1001, [float("nan")] * 12), (1002, [1.0, None])]
    df = topk.scaled(spark.createDataFrame(rows + bad, "id long, e array<float>"), "id", "e", 1024)
    got = topk.search(df, df.filter("id % 100 = 0"), 10, shard_rows=150, block_rows=2)
    whole = [(i, [int(np.floor(1024 * x)) for x in v]) for i, v in rows]
    assert sorted(tuple(x) for x in got.collect()) == brute_top(whole, 10)


def test_topk_probes_few_rows():
    """The threshold rises: rows are passed over, and of the others only part is probed, with exact results."""
    r = np.random.default_rng(4)
    centers = r.normal(size=(30, 32))
    rows = np.floor(1024 * (centers[r.integers(0, 30, 6000)] + 0.3 * r.normal(size=(6000, 32)))).astype(np.int64)
    ids = np.arange(6000)
    shard = topk.Shard(ids, rows)
    asked = range(0, 6000, 500)
    for i in asked:
        score = rows @ rows[i]
        want = np.lexsort((ids[ids != i], -score[ids != i]))[:10]
        found, got = shard.search(rows[i], i, 10)
        assert found.tolist() == ids[ids != i][want].tolist() and got.tolist() == score[ids != i][want].tolist()
    n = len(asked) * 6000
    assert shard.work[0] == n and shard.work[1] < 0.5 * n and shard.work[2] < 0.8 * n * 32
    # a threshold from elsewhere leaves out only what is below it
    _, got = shard.search(rows[0], 0, 10, least=int(np.sort(rows[1:] @ rows[0])[-4]))
    assert got.tolist()[:4] == sorted((rows[1:] @ rows[0]).tolist(), reverse=True)[:4]


def test_topk_of_large_numbers(spark):
    """Products beyond 2**53 are summed as longs."""
    r = np.random.default_rng(8)
    rows = [(i, [int(x) for x in v]) for i, v in enumerate(r.integers(-(2**30), 2**30, (300, 6)))]
    df = spark.createDataFrame(rows, "id long, v array<long>")
    got = topk.search(df, df.filter("id % 100 = 0"), 10, shard_rows=60, block_rows=2)
    assert sorted(tuple(x) for x in got.collect()) == brute_top(rows, 10)


def test_topk_empty(spark):
    df = topk.scaled(spark.createDataFrame([], "id long, e array<float>"), "id", "e", 1024)
    assert topk.search(df, df, 10).count() == 0


# 2 ----------------------------------------------------------------------------------------------------


def test_shards_move_little_and_follow_weights(spark):
    df = spark.range(6000).withColumnRenamed("id", "k")
    rows = sharding.reshard(df, "k", [1.0] * 8, [1.0] * 9).collect()
    assert all(r.shard_after == 8 for r in rows if r.moves) and 400 < sum(r.moves for r in rows) < 950
    n = Counter(r.shard for r in sharding.shard_records(df, "k", [1.0, 3.0, 0.0]).collect())
    assert n[2] == 0 and 2.6 < n[1] / n[0] < 3.4


def test_slots_are_gapless(spark, docs, empty):
    placed = sharding.numbered(sharding.shard_records(docs, "doc_id", [1.0] * 3), ["shard"], ["doc_id", "text"], "slot")
    by = {}
    for r in placed.collect():
        by.setdefault(r.shard, []).append(r.slot)
    assert all(sorted(v) == list(range(len(v))) for v in by.values()) and sum(map(len, by.values())) == docs.count()
    assert sharding.shard_records(empty, "doc_id", [1.0]).count() == 0


# 3 ----------------------------------------------------------------------------------------------------


def brute_targets(sizes, weights, share, cap):
    names = sorted((s for s in sizes if s is not None)) + [s for s in sizes if s is None]
    w = {s: weights[i % len(weights)] for i, s in enumerate(names)}
    left, full, target = share * sum(sizes.values()), set(), {}
    while True:
        open_ = [s for s in names if s not in full]
        unit = left / sum(w[s] for s in open_) if open_ else 0
        over = [s for s in open_ if unit * w[s] > cap * sizes[s]]
        if not over:
            return target | {s: unit * w[s] for s in open_}
        for s in over:
            full.add(s)
            target[s] = cap * sizes[s]
            left -= target[s]


def test_mix_meets_targets(spark, docs, empty):
    more = spark.createDataFrame([(100 + i, words(rng.randint(1, 60)), None, None if i % 4 == 0 else f"s{i % 7}", 1, "", "", "", "") for i in range(400)], SCHEMA)
    whole = docs.unionByName(more)
    rows = mixing.mix(whole).collect()
    assert len(rows) == whole.count()
    sizes = Counter()
    for r in rows:
        sizes[r.source] += r["size"]
    want = brute_targets(sizes, [5, 2, 1], 1.5, 2)
    taken = Counter()
    for r in rows:
        assert 0 <= r.copies <= 2 and r.source_size == sizes[r.source] and abs(r.target - want[r.source]) < 1e-6
        taken[r.source] += r.copies * r["size"]
    assert all(abs(taken[s] - want[s]) <= 30 for s in sizes)
    assert sorted(map(str, mixing.mix(whole.repartition(7)).collect())) == sorted(map(str, rows))
    assert mixing.mix(empty).count() == 0


# 4 ----------------------------------------------------------------------------------------------------


def brute_lines(texts, least):
    key = lambda x: x.strip(" \t\n\x0b\x0c\r").translate({c: c + 32 for c in range(65, 91)})
    lines = [(t or "").split("\n") for t in texts]
    n = Counter(k for own in lines for k in {key(x) for x in own})
    return [(len(own), "\n".join(x for x in own if not (key(x) and n[key(x)] >= least))) for own in lines]


@pytest.mark.parametrize("most", [1_000_000, 0])
def test_lines(docs, empty, most):
    rows = docs.orderBy("doc_id").collect()
    want = brute_lines([r.text for r in rows], 10)
    got = line_dedup.dedup_lines(docs, 10, broadcast_keys=most).orderBy("doc_id").collect()
    assert [(r.n_lines, r.kept) for r in got] == want
    assert line_dedup.dedup_lines(empty).count() == 0


def test_lines_are_reversible(docs):
    whole = line_dedup.line_counts(docs)
    part = docs.filter("doc_id % 3 = 0")
    undone = line_dedup.apply_changes(line_dedup.apply_changes(whole, inserted=part), deleted=part)
    assert sorted(map(tuple, undone.collect())) == sorted(map(tuple, whole.collect()))


@pytest.mark.parametrize("most", [1_000_000, 0])
def test_one_document_keeps_a_line(spark, docs, most):
    """keep="first": every frequent line stays in one document, of exact copies in one and the same; equal rows keep it together."""
    copies = "a first line\nand a second one\n\nthird"
    more = spark.createDataFrame([(300 + i, copies, None, None, 1, "", "", "", "") for i in range(14)], SCHEMA)
    rows = line_dedup.dedup_lines(docs.unionByName(more), 10, keep="first", broadcast_keys=most).collect()
    whole = [r for r in rows if r.doc_id >= 300]
    assert sorted(r.kept for r in whole) == [""] * 13 + [copies]
    assert all(r.n_lines == 4 and r.n_dropped == (0 if r.kept else 3) for r in whole)
    shared = [r for r in rows if r.doc_id < 300 and any(x.strip().lower() == "shared line" for x in r.kept.split("\n"))]
    assert len(shared) == 1
    assert sum("shared line" in (r.text or "").lower() for r in rows) == 12


def test_filters_follow_documents(spark, docs, monkeypatch):
    """Inserted and deleted documents change only the shards of keys that cross the threshold, and the changed filters are as good as new ones."""
    monkeypatch.setattr(line_dedup, "SHARD_KEYS", 16)
    lines = [f"line number {i}" for i in range(200)]
    first = spark.createDataFrame([(i, "\n".join(rng.sample(lines, 60))) for i in range(30)], "doc_id long, text string")
    gone = first.filter("doc_id < 6")
    before = line_dedup.stored(line_dedup.line_counts(first), "counts")
    bits = line_dedup.shard_bits(before.filter("n >= 8").count())
    assert bits >= 3
    filters = line_dedup.stored(line_dedup.build_filters(before.filter("n >= 8"), bits), "filters")
    after = line_dedup.stored(line_dedup.apply_changes(before, inserted=None, deleted=gone), "counts")
    changed = line_dedup.stored(line_dedup.change_filters(filters, bits, before, after, 8), "filters")
    h = lambda t, least: np.array([r.h1 for r in t.filter(f"n >= {least}").collect()], np.int64).view(np.uint64)
    known = lambda f: line_dedup.Known(bits, {r.shard: line_dedup.CuckooFilter.from_bytes(r.filter) for r in f.collect()}, *[np.zeros(0, np.uint64)] * 2, np.zeros(0, np.int64))
    now, was = h(after, 8), h(before, 8)
    fell = np.setdiff1d(was, now)
    assert len(fell) and known(changed).may_hold(now).all() and known(changed).may_hold(fell).mean() < 0.1 and known(filters).may_hold(fell).all()
    touched = {int(x >> np.uint64(16)) & ((1 << bits) - 1) for x in np.setxor1d(was, now).tolist() for x in [np.uint64(x)]}
    old, new = ({r.shard: bytes(r.filter) for r in f.collect()} for f in (filters, changed))
    assert {s for s in new if new[s] != old.get(s)} <= touched
    # the scan asks the kept filters on both paths
    rest = first.filter("doc_id >= 6")
    want = brute_lines([r.text for r in rest.orderBy("doc_id").collect()], 8)
    for most in (1_000_000, 0):
        got = line_dedup.drop_frequent(rest, after, 8, broadcast_keys=most, filters=changed, bits=bits).orderBy("doc_id").collect()
        assert [(r.n_lines, r.kept) for r in got] == want


def test_long_lines_are_counted_in_parts(spark, monkeypatch):
    monkeypatch.setattr(line_dedup, "HELD_BYTES", 1000)
    df = spark.createDataFrame([(i, "x" * 5000 + "\n" + "y" * (900 + i % 2)) for i in range(12)], "doc_id long, text string").repartition(2)
    assert sorted(r.n for r in line_dedup.line_counts(df).collect()) == [6, 6, 12]
    assert {r.kept for r in line_dedup.dedup_lines(df, 7).collect()} == {"y" * 900, "y" * 901}


def test_cuckoo_filter_inserts_and_deletes():
    r = np.random.default_rng(1)
    h = r.integers(0, 1 << 63, 5000, dtype=np.uint64)
    f = line_dedup.CuckooFilter(len(h))
    for x in h.tolist():
        f.insert(x)
    assert f.contains(h).all() and f.contains(r.integers(0, 1 << 63, 20000, dtype=np.uint64)).mean() < 0.01
    assert all(f.delete(x) for x in h[:2500].tolist())
    assert f.contains(h[2500:]).all() and f.contains(h[:2500]).mean() < 0.01


# 5 ----------------------------------------------------------------------------------------------------


def brute_best_fit(lengths, capacity):
    windows = []
    for n in sorted(lengths, reverse=True):
        fit = [w for w in windows if capacity - w >= n]
        if fit:
            windows[windows.index(max(fit))] += n
        else:
            windows.append(n)
    return sorted(windows)


def test_plan_is_best_fit_decreasing():
    for seed in range(20):
        r = random.Random(seed)
        lengths = [r.randint(1, 64) for _ in range(r.randint(0, 300))]
        fill = Counter()
        for length, rank, first, each, offset in packing.plan(Counter(lengths), 64):
            assert offset + length * each <= 64
        rules = sorted(packing.plan(Counter(lengths), 64))
        for n, count in Counter(lengths).items():
            own = [x for x in rules if x[0] == n]
            for rank in range(count):
                _, start, first, each, offset = max(x for x in own if x[1] <= rank)
                fill[first + (rank - start) // each] += n
        assert sorted(fill.values()) == brute_best_fit(lengths, 64)


def test_packing_keeps_all_ids(docs, empty):
    from tokenizers import Tokenizer

    path = packing.default_vocabulary()
    slow, fast = Tokenizer.from_file(path), packing.encoder(path)
    for t in ["", "a<|endoftext|>b", "  x\n\n y ", "漢字😀 it's 12", *words(50).split()]:
        assert fast(t).tolist() == slow.encode(t, add_special_tokens=False).ids
    packed = packing.pack(docs, path, capacity=128, keep_ids=True)
    rows = packed.collect()
    assert Counter(r.doc_id for r in rows if r.start == 0) == Counter(r.doc_id for r in docs.collect())
    by = {}
    for r in rows:
        assert zlib.crc32(np.array(r.ids, "<u4").tobytes()) == r.ids_crc32 and len(r.ids) == r.length
        by.setdefault(r.sequence_id, []).append((r.offset, r.length))
    for own in by.values():
        at = 0
        for offset, n in sorted(own):
            assert offset == at
            at += n
        assert at <= 128
    assert sorted(by) == list(range(len(by)))
    for r in packing.sequences(packed, 128).collect():
        assert len(r.ids) == 128 or len(r.ids) & (len(r.ids) - 1) == 0
    assert packing.pack(empty, path).count() == 0


# 6 ----------------------------------------------------------------------------------------------------


def test_avi_round_trip():
    r = np.random.default_rng(2)
    for n in (64, 128, 4096, 4160, 64 * 333):
        for payload in (r.integers(0, 256, n, dtype=np.uint8).tobytes(), b"\xff" * n, b"\0" * n):
            media = avi.store_payload(payload)
            film = avi.read_avi(media)
            heads = [avi.Jpeg(f) for f in film["frames"]]
            assert b"".join(avi.payload_of(c).tobytes() for c in avi.decode(heads)) == payload
            index = media.rindex(b"idx1")
            assert avi.read_avi(media[:index])["frames"] == film["frames"]  # without its index


def test_avi_shots(spark):
    dark, light = bytes([128] + [0] * 63), bytes([255] * 64)
    film = avi.write_avi([avi.write_frames(np.frombuffer(b, np.uint8))[0] for b in [dark] * 12 + [light] * 9], 8, 8)
    got = avi.clips(spark.createDataFrame([(1, bytearray(film)), (2, None), (3, bytearray(b"RIFFxxxx"))], "k long, m binary"), "k", "m").orderBy("k", "clip").collect()
    assert [(r.k, r.first_frame, r.last_frame, r.start_ms) for r in got if r.error is None] == [(1, 0, 11, 0), (1, 12, 20, 480)]
    assert [r.k for r in got if r.error] == [3]


def test_avi_digests(docs, empty):
    for r in avi.digests(docs).join(docs.select("doc_id", "text"), "doc_id").collect():
        raw = (r.text or "").encode()
        payload = raw + b"\0" * (-len(raw) % 64 if raw else 64)
        assert (r.n_bytes, r.payload_bytes, r.payload_sha256, r.tail_crc32) == (len(raw), len(payload), hashlib.sha256(payload).hexdigest(), zlib.crc32(payload[-64:]))
    assert avi.digests(empty).count() == 0


# 7 ----------------------------------------------------------------------------------------------------


def test_main_text(spark):
    def page(i):
        return f"<html><head><title>t</title><script>var a='</p>';</script></head><body><nav><a>menu {i}</a></nav><div class='site-note'>Same words on all pages</div><div><p>Own story {i} &amp; more<br>of&nbsp;it<p>second <b>bold</b></div><div class=comments>me too {i}</div><footer>x</footer>"

    rows = [(i, "http://a.example/x", page(i)) for i in range(8)] + [(8, None, None), (9, "x", ""), (10, "http://b.example", "<p>plain"), (11, "http://c.example", "<main><h1>A</h1> b </main> side")]
    df = spark.createDataFrame([(*r, "clash") for r in rows], "page_id long, url string, html string, text string")
    got = {r.page_id: r.text for r in html_text.extract(df).collect()}
    assert got[3] == "Own story 3 & more of it\n\nsecond bold"
    assert (got[8], got[9], got[10], got[11]) == ("", "", "plain", "A\n\nb")
    assert html_text.extract(df.limit(0)).count() == 0


@pytest.mark.parametrize("broadcast", [500_000, 0])
def test_main_text_of_copies(spark, monkeypatch, broadcast):
    monkeypatch.setattr(html_text, "BROADCAST_COPIES", broadcast, raising=False)
    page = lambda body: f"<html><body><nav>Menu</nav><article><h1>{body[:9]}</h1><p>{body}</p></article></body></html>"
    own = [words(20) for _ in range(5)]
    rows = [("http://twice/a", page("only one page here"))] * 2
    rows += [("http://mostly/a", page("a page in many copies"))] * 95 + [(f"http://mostly/{i}", page(own[i])) for i in range(5)]
    df = spark.createDataFrame([(i, *r) for i, r in enumerate(rows)], "page_id long, url string, html string").repartition(4)
    got = {r.page_id: r.text for r in html_text.extract(df).collect()}
    assert {got[0], got[1]} == {"only one\n\nonly one page here"}
    assert {got[i] for i in range(2, 97)} == {"a page in\n\na page in many copies"}
    assert [got[97 + i] for i in range(5)] == [f"{t[:9].strip()}\n\n{t}" for t in own]
    assert html_text.style_tree(df).filter("host = 'mostly' and path = '/html/body/article'").first().pages == 6


def test_main_text_of_wrappers(spark):
    text = words(30)
    article = f"<article><div class='entry-header'><h1>Title</h1></div><p>{text}</p><div class=share>Share this</div></article>"
    whole = f"Title\n\n{text}"
    for name in ("has-sidebar", "no-sidebar", "nav-open", "comments-open", "social-layout"):
        assert html_text.main_text(f"<body><nav>Menu</nav><div id=page class='{name}'>{article}<div class=sidebar>Links</div></div>") == whole
        assert html_text.main_text(f"<body><div class='{name}'><h1>Title</h1><p>{text}</p><div class=sidebar>Links</div></div><p>end") == f"{whole}\n\nend"
        assert html_text.main_text(f"<body><section class='{name}'><p>{text}</p></section>") == text
    assert html_text.main_text(f"<body>{article}<div class=related><article>Teaser {words(90)}</article></div><div id=comments>{words(90)}</div>") == whole
    # most of the text is the same on all pages of the host, so the wrapper holds most of what counts
    same, own = words(200), [words(30) for _ in range(8)]
    rows = [(i, f"http://wrapped/{i}", f"<body><div class=about>{same}</div><div class=has-sidebar><p>{own[i]}</p></div></body>") for i in range(8)]
    got = html_text.extract(spark.createDataFrame(rows, "page_id long, url string, html string")).collect()
    assert {r.page_id: r.text for r in got} == dict(enumerate(own))


def test_the_style_tree_decides(spark, monkeypatch):
    """No article elements, class names of no list: same words and same shapes go by entropy alone, with and without the priors."""
    own = [words(25) for _ in range(12)]
    rows = []
    for i in range(12):
        tail = "".join(f"<p>{words(6)}</p>" for _ in range(i % 4))
        body = f"<div class=kx1><span>Start</span> <span>Contact us</span></div><div class=q9><p>{own[i]}</p>{tail}<div class=zz>All rights with the makers</div></div><div class=kx2><p>We use small files</p></div>"
        rows.append((i, f"http://plain/{i}", f"<body>{body}</body>"))
    df = spark.createDataFrame(rows, "page_id long, url string, html string")
    texts = lambda **how: {r.page_id: r.text for r in html_text.extract(df, **how).collect()}
    got = texts()
    assert all(t.split("\n\n")[0] == own[i] and len(t.split("\n\n")) == 1 + i % 4 for i, t in got.items())
    assert texts(roles=False) == got
    with monkeypatch.context() as m:
        m.setattr(html_text, "BROADCAST_PATHS", 0)
        assert texts() == got
    assert all("Contact us" in t and "All rights" in t and "small files" in t for t in texts(threshold=0.0).values())


def brute_tree(pages):
    """Composite importance of each path, from the definition."""
    import math

    seen = [html_text.segments(p) for p in pages]
    paths = {x[0] for own in seen for x in own}
    below = lambda p: [q for q in paths if q and q.rpartition("/")[0] == p]

    def entropy(counts):
        total = sum(counts)
        return -sum(c / total * math.log(c / total) for c in counts)

    def worth(p):
        n = sum((p, 0, 0) in own for own in seen)
        kinds = [Counter(v for own in seen for q, k, v in own if q == p and k == kind) for kind in (1, 2)]
        own = entropy(kinds[0].values()) / math.log(n) if n > 1 else 1.0
        # a segment on c of n pages has the entropy ln c in units of ln n; the mean weighs each by its pages
        m = sum(kinds[1].values())
        text = None if not m else 1.0 if n == 1 else 1 - min(1.0, sum(c * math.log(c) for c in kinds[1].values()) / m / math.log(n))
        parts = [(worth(q)[0], sum((q, 0, 0) in x for x in seen)) for q in below(p)] + ([(text, n)] if text is not None else [])
        if not parts:
            return 1.0, 1.0, n
        share = html_text.DAMPING ** len(parts)
        value = (1 - share) * own + share * sum(w * k for w, k in parts) / sum(k for _, k in parts)
        return value, max([value, text or 0.0, *(worth(q)[1] for q in below(p))]), n

    return {p for p in paths for _, best, n in [worth(p)] if best < html_text.THRESHOLD and n > 1 and html_text._NAME.match(p.rpartition("/")[2])[0] not in html_text.INLINE}


def test_low_branches_are_those_of_the_definition(spark):
    r = random.Random(11)
    some = ["<p>alpha beta</p>", "<p>gamma</p>", "<div class=m><p>same here</p><i>x</i></div>", "<div id=n9>one <b>two</b></div>", "<ul><li>a<li>b</ul>"]
    for trial in range(4):
        pages = ["<body>" + "".join(r.choice([x, x, f"<p>{words(3)}</p>", f"<div class=w{r.choice('ab')}><p>{words(2)}</p></div>", ""]) for x in some) + "</body>" for _ in range(r.randint(2, 9))]
        pages = sorted(set(pages))
        df = spark.createDataFrame([(i, "http://h/x", p) for i, p in enumerate(pages)], "page_id long, url string, html string")
        low = html_text.low_branches(html_text.style_tree(df)).collect()
        assert {p for row in low for p in row.low} == (brute_tree(pages) if len(pages) > 1 else set()), trial


def test_teasers_are_not_the_text():
    text = words(60)
    teasers = "".join(f"<article><h2>{words(2)}</h2></article>" for _ in range(3))
    assert html_text.main_text(f"<body><div class=q><h1>Head</h1><p>{text}</p></div>{teasers}").startswith(f"Head\n\n{text}")
    assert html_text.main_text(f"<body><article><p>{text}</p></article><article><p>{text}</p></article><p>{words(9)}</p>") == f"{text}\n\n{text}"


# 8 ----------------------------------------------------------------------------------------------------


def test_toxicity_learns(spark, empty):
    rows = []
    for i in range(400):
        t = words(30).split()
        if i % 4 == 0:
            t[rng.randrange(30)] = rng.choice(["awfulword", "nastyword"])
        rows.append((i, " ".join(t), int(i % 4 == 0)))
    df = spark.createDataFrame(rows, "key long, text string, label int")
    model = toxicity.train(df.filter("key < 300"), 300)
    got = toxicity.predict(df.filter("key >= 300"), model).collect()
    assert sum(r.predicted == r.label for r in got) >= 0.97 * len(got) and all(0 <= r.score <= 1 for r in got)
    none = toxicity.train(df.limit(0), 0)
    assert toxicity.predict(spark.createDataFrame([(1, None), (2, "")], "doc_id long, text string"), none).filter("score between 0 and 1").count() == 2
    assert toxicity.predict(empty, model).count() == 0


# 9 ----------------------------------------------------------------------------------------------------


def brute_sets(texts):
    out = []
    for t in texts:
        w = "".join(c.lower() if "A" <= c <= "Z" else c for c in t or "")
        for s in "\t\n\x0b\x0c\r":
            w = w.replace(s, " ")
        w = [x for x in w.split(" ") if x]
        out.append({tuple(w[i : i + 5]) for i in range(max(1, len(w) - 4))} if w else set())
    return out


def brute_components(ids, own):
    comp = {i: i for i in ids}
    for _ in ids:
        for a, s in zip(ids, own, strict=True):
            for b, t in zip(ids, own, strict=True):
                if s and t and 100 * len(s & t) >= 75 * len(s | t):
                    comp[a] = comp[b] = min(comp[a], comp[b])
    return comp


@pytest.mark.parametrize("long", [2, 16])
def test_near_duplicates(spark, docs, empty, long):
    base = [words(40).split() for _ in range(3)]
    many = []
    for i in range(60):
        t = list(base[i % 3])
        for _ in range(rng.randint(0, 3)):
            t[rng.randrange(40)] = rng.choice(VOCABULARY)
        many.append((200 + i, " ".join(t)))
    df = docs.select("doc_id", "text").unionByName(spark.createDataFrame(many, "doc_id long, text string"))
    rows = df.collect()
    own = brute_sets([r.text for r in rows])
    want = brute_components([r.doc_id for r in rows], own)
    got = near_dup.near_duplicates(df, long=long).collect()
    assert sorted((r.doc_id, r.component_id) for r in got) == sorted((r.doc_id, want[r.doc_id]) for r in rows)
    assert Counter((r.doc_id, r.n_shingles) for r in got) == Counter((r.doc_id, len(s)) for r, s in zip(rows, own, strict=True))
    assert near_dup.near_duplicates(empty).count() == 0


def test_long_words_and_texts(monkeypatch):
    import pyarrow as pa

    t = [words(900), "a" * 5000, " ".join(["b"] * 700)]
    want = [s.tolist() for s in shingles.sets(pa.array(t))]
    monkeypatch.setattr(shingles, "SEGMENT", 256)
    assert [s.tolist() for s in shingles.sets(pa.array(t))] == want


def test_word_hashes_depend_on_bytes_alone():
    import pyarrow as pa

    passage = " ".join(f"p{i}" for i in range(1000))
    (want,) = shingles.sets(pa.array([passage]))
    before, after = " ".join(f"b{i}" for i in range(260_000)), " ".join(f"a{i}" for i in range(30_000))
    for size in (4096, 4097, 150_000, 2_200_000):
        for cut in (0, 700_001, 1_880_000):
            text = f"{before[:cut]} {passage} {before[cut:1_950_000]} {'X' * size} {passage} {after} {passage}"
            (got,) = shingles.sets(pa.array([text]))
            assert np.isin(want, got).all()
            n = len(text.split())
            # every passage after the first adds only the shingles that cross its ends
            assert len(got) == n - shingles.WIDTH + 1 - 2 * len(want)
    (low,), (high,) = (list(shingles.sets(pa.array([x * 9000]))) for x in ("x", "X"))
    assert low.tolist() == high.tolist()


# 10 ---------------------------------------------------------------------------------------------------


def test_language(spark, empty):
    r = random.Random(5)
    make = {"aa": lambda: "".join(r.choice("abcd") for _ in range(6)), "bb": lambda: "".join(r.choice("wxyz") for _ in range(6))}
    rows = [(i, " ".join(make[k]() for _ in range(20)), k) for i, k in enumerate(["aa", "bb"] * 100)]
    df = spark.createDataFrame([*rows, (900, None, "aa"), (901, "12 !?", "bb"), (902, "", None)], "doc_id long, text string, lang string")
    got = {x.doc_id: x for x in language.predict(df, language.train(df.filter("doc_id < 150"))).collect()}
    assert all(got[i].lang_pred == k for i, _, k in rows) and all(got[i].lang_pred == "und" and got[i].score == 0 for i in (900, 901, 902))
    assert language.predict(empty, language.train(empty)).count() == 0
    assert {x.lang_pred for x in language.predict(df, language.train(empty)).collect()} == {"und"}


def test_more_languages_than_a_word_has_bits(spark):
    """70 languages of three letters each, and one whose only text repeats no n-gram."""
    r = random.Random(6)
    letters = {f"l{k:02d}": [chr(0x4E00 + 3 * k + i) for i in range(3)] for k in range(70)}
    rows = [(i, " ".join("".join(r.choice(letters[k]) for _ in range(5)) for _ in range(12)), k) for i, k in enumerate(sorted(letters) * 4)]
    rows.append((900, "abcdefg", "zz"))
    df = spark.createDataFrame(rows, "doc_id long, text string, lang string")
    got = {x.doc_id: x.lang_pred for x in language.predict(df, language.train(df.filter("doc_id < 210 or doc_id = 900"))).collect()}
    assert got == {i: k for i, _, k in rows}


# pipeline ---------------------------------------------------------------------------------------------


def test_pipeline_stages(spark, docs, empty):
    import corpus_pipeline as pipe
    from cutline.llm.common import stored

    now, before = docs, docs.count()
    for _name, stage in pipe.STAGES[:-1]:
        now = stored(stage(spark, now, ""), "test")
        assert now.columns == pipe.COLUMNS
    first = stored(pipe.STAGES[0][1](spark, docs, ""), "test")
    assert first.count() == docs.filter("text rlike '\\\\p{L}'").count() < before
    third = stored(pipe.STAGES[2][1](spark, first, ""), "test").collect()
    own = [(r.doc_id, r.text) for r in first.collect()]
    want = brute_components([i for i, _ in own], brute_sets([t for _, t in own]))
    assert sorted(r.doc_id for r in third) == sorted(set(want.values()))
    packed = pipe.STAGES[-1][1](spark, now, "").collect()
    assert Counter(r.doc_id for r in packed if r.start == 0) == Counter(r.doc_id for r in now.collect())
    gone = empty
    for _name, stage in pipe.STAGES:
        gone = stored(stage(spark, gone, ""), "test")
    assert gone.count() == 0
