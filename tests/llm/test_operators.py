"""The ten operators against brute force on small tables with awkward rows."""

import collections
import hashlib
import random
import re
import zlib

import numpy as np
import pytest
import xxhash
from pyspark.sql import functions as F

from cutlearn.llm import chat, components, decontam, html_extract, langid, line_dedup, mixing, near_jaccard, quality, simhash, suffix_dedup, warc
from cutlearn.llm import queries as Q
from tests.conftest import SF, same_rows

DOCS = "doc_id long, text string, lang string, source string, n_chars long"
WORD = re.compile(r"[^\x20\x09-\x0D]+")


def prose(rng, n):
    return " ".join(rng.choice("the of And éa house;tree run# x1 über 你好 a".split()) + str(rng.randrange(50)) * (rng.random() < 0.5) for _ in range(n))


@pytest.fixture(scope="module")
def awkward():
    rng = random.Random(4)
    long = prose(rng, 3000)
    texts = [None, "", " \t\n ", "x", "two words", "\n\n", long, long, long[:9000] + " edit " + long[9006:], prose(rng, 300) * 2, "aaaa" * 500, "ab" * 900 + "c", "ÉCOLE\nThe same line here\nTHE SAME LINE HERE \nend", "the same line here\nother"]
    shared = prose(rng, 120)
    texts += [prose(rng, 60) + " " + shared + " " + prose(rng, 40) for _ in range(6)]
    rows = [(k, t, "en", f"s{k % 3}" if k % 5 else None, len(t or "")) for k, t in enumerate(texts)]
    rows += [(6, long, "en", "s0", len(long)), (None, shared + " null id", "fr", None, 5), (None, None, None, None, None), (3, "x", "en", "s0", 1)]
    return rows


def frame(spark, rows):
    return spark.createDataFrame(rows, DOCS).repartition(3)


def clashing(df):
    """The table with columns whose names the operators use themselves."""
    names = "kept stay times size share block th s e n h1 h2 pos line key fp dropped text_hash copy copies score contaminated item_id lang_pred plan".split()
    return df.select("*", *(F.lit(k).alias(c) for k, c in enumerate(names)))


# op 1 ----------------------------------------------------------------------------------------------------------------


def removed_by_brute_force(rows, span=400):
    raw = [(i, (t or "").encode()) for i, t, *_ in rows]
    seen = collections.Counter(r[k : k + span] for _, r in raw for k in range(len(r) - span + 1))
    out = []
    for i, r in raw:
        gone = np.zeros(len(r), bool)
        for k in range(len(r) - span + 1):
            if seen[r[k : k + span]] > 1:
                gone[k : k + span] = True
        left = np.frombuffer(r, np.uint8)[~gone].tobytes()
        runs = int((np.diff(np.concatenate([[0], gone.astype(int)])) == 1).sum())
        out.append((i, len(r), int(gone.sum()), runs, hashlib.sha256(left).hexdigest()))
    return sorted(out, key=str)


@pytest.mark.parametrize("per_shard", [suffix_dedup.SHARD_SEGMENTS, 2])
def test_suffix_dedup(spark, awkward, per_shard):
    got = suffix_dedup.remove_repeats(clashing(frame(spark, awkward)), per_shard).drop("kept").collect()
    assert sorted(map(tuple, got), key=str) == removed_by_brute_force(awkward)


def test_suffix_dedup_across_shards(spark):
    """One anchor with very many different segments, dealt to many shards."""
    rng = random.Random(1)
    base = "".join(rng.choice("abcdefgh ") for _ in range(1100))
    rows = []
    for k in range(40):
        t = list(base)
        for _ in range(2):
            t[rng.randrange(len(t))] = "Z"
        rows.append((k, "".join(t), "en", "s", 0))
    got = suffix_dedup.remove_repeats(frame(spark, rows), 3).drop("kept").collect()
    assert sorted(map(tuple, got), key=str) == removed_by_brute_force(rows)


def test_long_texts_are_hashed_in_pieces(spark, monkeypatch):
    rng = random.Random(3)
    long = "".join(rng.choice("abcdefgh ") for _ in range(9000))
    rows = [(1, long, "en", "s", 0), (2, "x" + long[1700:6200] + "y", "en", "s", 0), (3, long[:399] + "!" + long[8000:8500], "en", "s", 0)]
    whole = [len(x[1]) for x in suffix_dedup.pieces(np.zeros(9000, np.uint8), np.array([0, 9000]), long=1000)]
    assert whole == [1399] * 8 + [1000]
    raw = np.frombuffer(long.encode(), np.uint8)
    windows = lambda size: sorted((at + s + k, int(ah)) for at, d, o in suffix_dedup.pieces(raw, np.array([0, 9000]), long=size) for _, s, c, ah, _ in [x for x in zip(*suffix_dedup.anchors_of(d, o), strict=True)] for k in range(c))
    assert windows(1000) == windows(1 << 20)
    got = suffix_dedup.remove_repeats(frame(spark, rows)).drop("kept").collect()
    assert sorted(map(tuple, got), key=str) == removed_by_brute_force(rows)


def test_suffix_arrays_and_common_prefixes():
    rng = np.random.default_rng(0)
    for n in (1, 2, 40, 700):
        t = rng.integers(1, 3, n).astype(np.uint16)
        sa, _ = suffix_dedup.suffix_ranks(t, n)
        tails = [tuple(t[i:]) for i in range(n)]
        assert [tails[i] for i in sa] == sorted(tails)
    segments = [rng.integers(97, 99, int(k)).astype(np.uint8) for k in rng.integers(6, 50, 25)]
    windows = np.array([len(s) - 5 for s in segments])
    seg, off, cls = suffix_dedup.repeats_in_shard(segments, windows, 6)
    by = collections.defaultdict(set)
    for a, b, c in zip(seg, off, cls, strict=True):
        by[segments[a][b : b + 6].tobytes()].add(int(c))
    assert all(len(v) == 1 for v in by.values()) and len({min(v) for v in by.values()}) == len(by)


def test_every_window_has_an_anchor_and_equal_windows_equal_ones():
    rng = np.random.default_rng(2)
    data = np.tile(rng.integers(97, 101, 700).astype(np.uint8), 3)
    offsets = np.array([0, 900, 1300, 2100])
    doc, start, count, ah, _ = suffix_dedup.anchors_of(data, offsets)
    assert count.sum() == (np.maximum(np.diff(offsets) - 399, 0)).sum()
    seen = {}
    for s, c, h in zip(start, count, ah, strict=True):
        for w in range(s, s + c):
            assert seen.setdefault(data[w : w + 400].tobytes(), h) == h


# op 2 ----------------------------------------------------------------------------------------------------------------


def base_measures(t):
    w = WORD.findall(t or "")
    triples = collections.Counter(tuple(w[k : k + 3]) for k in range(len(w) - 2))
    again = {k + j for k in range(len(w) - 2) if triples[tuple(w[k : k + 3])] > 1 for j in range(3)}
    lines, seen, dup = (t or "").split("\n"), set(), 0
    for x in lines:
        if WORD.search(x):
            dup += x in seen
            seen.add(x)
    return len(w), sum(map(len, w)), sum((t or "").count(c) for c in "#*$%&|<>"), dup, len(again)


def test_quality_measures(spark, awkward):
    labels = spark.createDataFrame([(6, 1, 0), (9, 1, 0), (None, 1, 0), (14, 0, 0), (6, 1, 0)], "doc_id long, quality int, toxic int")
    got = quality.quality_rules(clashing(frame(spark, awkward)), labels).collect()
    names = ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words")
    assert sorted((str(r.doc_id), *(r[c] for c in names)) for r in got) == sorted((str(i), *base_measures(t)) for i, t, *_ in awkward)
    for r in got:
        assert r.base_failed == (r.n_words < 50 or 100 * r.n_repeat_words > 50 * r.n_words)
        assert r.kept == (not r.base_failed and r.llr_micro >= quality.THRESHOLD * r.n_grams)


def test_quality_score_by_hand():
    """The log ratio of a text is the plain sum over its n-grams, whatever the slices."""
    texts = ["One two  three", "", "über two"]
    weights = np.random.default_rng(0).integers(-1000, 1000, quality.BUCKETS)
    import pyarrow as pa

    from cutlearn.llm import textblocks as tb

    def parts(ts):
        data, offsets = tb.column_bytes(pa.array(ts))
        return quality.measure(data, offsets, weights)[-2:]

    n, total = parts(texts)
    assert n.tolist() == [3 + 2 + 11, 0, 2 + 1 + 6]
    for k, t in enumerate(texts):
        one = parts([t])
        assert (one[0][0], one[1][0]) == (n[k], total[k])


def test_quality_keeps_good_and_drops_junk(spark):
    docs, labels = (spark.read.parquet(f"/root/testdata/sf0.01/{t}.parquet") for t in ("documents", "labels"))
    got = quality.quality_rules(docs, labels).where("not base_failed").join(labels, "doc_id")
    assert got.where("quality = 1 and not kept").count() == 0 and got.where("quality = 0 and kept").count() == 0


def test_quality_without_labels_keeps_all_that_pass(spark, awkward):
    none = spark.createDataFrame([], "doc_id long, quality int, toxic int")
    got = quality.quality_rules(frame(spark, awkward), none).collect()
    assert all(r.kept != r.base_failed for r in got)


# op 3 ----------------------------------------------------------------------------------------------------------------


def fingerprint(t):
    w = WORD.findall("".join(c.lower() if "A" <= c <= "Z" else c for c in t or ""))
    s = [" ".join(w[k : k + 3]) for k in range(len(w) - 2)] if len(w) > 2 else [" ".join(w)] * bool(w)
    h = [xxhash.xxh64_intdigest(x.encode(), 42) for x in s]
    return sum(1 << b for b in range(64) if 2 * sum(v >> b & 1 for v in h) > len(h))


def components_by_brute_force(rows):
    fps = [fingerprint(t) for _, t, *_ in rows]
    label = list(range(len(rows)))
    for _ in rows:
        for a in range(len(rows)):
            for b in range(len(rows)):
                if bin(fps[a] ^ fps[b]).count("1") <= 3:
                    label[a] = label[b] = min(label[a], label[b])
    least = {k: min((rows[j][0] for j in range(len(rows)) if label[j] == k and rows[j][0] is not None), default=None) for k in label}
    return sorted((str(r[0]), f"{f:016x}", str(least[k])) for r, f, k in zip(rows, fps, label, strict=True))


@pytest.mark.parametrize("hot", [simhash.HOT, 2])
def test_simhash(spark, awkward, hot):
    got = simhash.near_duplicates(clashing(frame(spark, awkward)), hot=hot).collect()
    assert sorted((str(r.doc_id), r.fingerprint, str(r.component_id)) for r in got) == components_by_brute_force(awkward)


def test_every_pair_within_the_radius_shares_a_table():
    rng = np.random.default_rng(0)
    tables = simhash.masks()
    assert len(tables) == 15
    for _ in range(3000):
        bits = rng.choice(64, rng.integers(0, 4), replace=False)
        diff = np.uint64(sum(1 << int(b) for b in bits))
        assert ((tables & diff) == 0).any()


@pytest.mark.parametrize("hot", [4096, 5, 1])
def test_links_lose_no_component(spark, hot):
    rng = np.random.default_rng(3)
    centre = rng.integers(0, 1 << 63, 30)
    fps = {int(c) for c in centre}
    for c in centre:
        for _ in range(12):
            x = int(c)
            for b in rng.choice(63, rng.integers(1, 6), replace=False):
                x ^= 1 << int(b)
            fps.add(x)
    fps = sorted(fps)
    found = simhash.links(spark.createDataFrame([(f,) for f in fps], "fp long"), hot=hot)
    assert found.count() < 15 * 4**2 * len(fps)
    root = {r.node: r.root for r in components.star_components(found).collect()}
    a = np.array(fps, np.uint64)
    label = {f: f for f in fps}
    changed = True
    while changed:
        changed = False
        for f in fps:
            for g in a[np.bitwise_count(a ^ np.uint64(f)) <= 3]:
                m = min(label[f], label[int(g)])
                changed |= label[f] != m or label[int(g)] != m
                label[f] = label[int(g)] = m
    assert {f: root.get(f, f) for f in fps} == label


def test_components_of_a_long_chain_and_loops(spark):
    rows = [(k, k + 1) for k in range(60)] + [(5, 5), (100, 101), (101, 100), (7, 6), (-3, 200), (-3, -9)]
    for few in (components.FEW, 0):  # union-find in one task, and rounds
        got = {r.node: r.root for r in components.star_components(spark.createDataFrame(rows, "a long, b long"), few=few).collect()}
        assert got == {**{k: 0 for k in range(1, 61)}, 101: 100, 200: -9, -3: -9}
        assert components.star_components(spark.createDataFrame([], "a long, b long"), few=few).count() == 0


def test_one_document_of_each_group_stays(spark, awkward):
    docs = clashing(frame(spark, awkward))
    kept = simhash.representatives(docs)
    want = {c for i, _, c in components_by_brute_force(awkward) if i == c != "None"}
    assert kept.columns == docs.columns
    assert sorted(str(r.doc_id) for r in kept.collect()) == sorted([*want, "None", "None"])


def similar_components(rows):
    def shingles(t):
        w = WORD.findall("".join(c.lower() if "A" <= c <= "Z" else c for c in t or ""))
        return {tuple(w[k : k + 5]) for k in range(len(w) - 4)} if len(w) > 4 else {tuple(w)}

    sets = [shingles(t) for _, t, *_ in rows]
    label = list(range(len(rows)))
    links = [(a, b) for a in range(len(rows)) for b in range(a) if 5 * len(sets[a] & sets[b]) >= 4 * len(sets[a] | sets[b])]
    for _ in rows:
        before = list(label)
        for a, b in links:
            label[a] = label[b] = min(label[a], label[b])
        if label == before:
            break
    least = {k: min((r[0] for j, r in enumerate(rows) if label[j] == k and r[0] is not None), default=None) for k in label}
    return sorted((str(r[0]), str(least[k])) for r, k in zip(rows, label, strict=True))


@pytest.mark.parametrize("block", [near_jaccard.BLOCK, 2])
def test_near_copies_of_the_pipeline(spark, awkward, block):
    import corpus_pipeline as P

    rng = random.Random(5)
    rows, at = list(awkward), 1000
    for size in (1, 4, 7, 24, 25, 60, 200):
        base = prose(rng, size).split()
        for _ in range(12):
            w = list(base)
            for _ in range(rng.randrange(1 + size // 30 + (size > 20))):
                w[rng.randrange(len(w))] = f"edit{rng.randrange(99)}"
            w = w[: len(w) - rng.randrange(1 + size // 8)]
            rows.append((at, " ".join(w), "en", "s", 1))
            at += 1
    passage = prose(rng, 40)
    rows += [(at + k, passage + " " + prose(rng, 20), "en", "s", 1) for k in range(40)]  # one passage, no near copies
    docs = clashing(frame(spark, rows))
    got = near_jaccard.components(docs, block).collect()
    want = similar_components(rows)
    assert sorted((str(r.doc_id), str(r.component_id)) for r in got) == want
    kept = P.near_copies(spark, docs, "")
    assert kept.columns == docs.columns
    assert sorted(str(r.doc_id) for r in kept.collect()) == sorted([*{i for i, c in want if i == c != "None"}, "None", "None"])


def test_sketches_bound_what_sets_share():
    rng = np.random.default_rng(3)
    pool = rng.integers(0, 1 << 63, 9000).astype(np.uint64)
    sets = [np.unique(rng.choice(pool[: 4 * n], n)) for n in (1, 5, 15, 17, 30, 33, 70, 300, 3000, 4000)]
    first = np.concatenate([[0], np.cumsum([len(x) for x in sets])])
    bits = near_jaccard.sketches(np.concatenate(sets), first).to_pylist()
    assert max(map(len, bits)) == near_jaccard.MOST_BITS // 8 and min(map(len, bits)) == 8
    zero = np.zeros(len(sets), np.int64)
    cell = near_jaccard.Cell({"n": np.diff(first), "rest": np.diff(first), "print": zero, "block": zero, "lo": zero, "hi": zero}, bits)
    others = np.arange(len(sets))
    for i, x in enumerate(sets):
        least = cell.common(i, others)
        assert least[i] == len(x)
        assert all(got >= len(np.intersect1d(x, y)) for got, y in zip(least, sets, strict=True))


# op 4 ----------------------------------------------------------------------------------------------------------------


def lines_by_brute_force(rows):
    key = lambda x: "".join(c.lower() if "A" <= c <= "Z" else c for c in x.strip(" \t\n\x0b\x0c\r"))
    holders = collections.defaultdict(set)
    for i, t, *_ in rows:
        for x in (t or "").split("\n"):
            if i is not None and len(key(x)) >= 10:
                holders[key(x)].add(i)
    out = []
    for i, t, *_ in rows:
        lines = (t or "").split("\n")
        kept = [x for x in lines if i is None or len(key(x)) < 10 or min(holders[key(x)]) == i]
        out.append((str(i), len(lines), len(lines) - len(kept), "\n".join(kept)))
    return sorted(out)


def test_line_dedup(spark, awkward, monkeypatch):
    rows = awkward + [(100 + k, "a very common line\nown line number %d\n A Very Common LINE\t\n\x0b" % k, "en", "s", 0) for k in range(80)]
    for hot_lines in (line_dedup.HOT_LINES, 10):
        monkeypatch.setattr(line_dedup, "HOT_LINES", hot_lines)
        got = line_dedup.dedup_lines(clashing(frame(spark, rows))).select("doc_id", "n_lines", "n_dropped", "kept").collect()
        assert sorted((str(r.doc_id), r.n_lines, r.n_dropped, r.kept) for r in got) == lines_by_brute_force(rows)


def test_line_dedup_has_no_python(spark):
    plan = line_dedup.dedup_lines(spark.read.parquet(f"{SF}/documents.parquet"))._jdf.queryExecution().executedPlan().toString()
    assert "Python" not in plan and "Arrow" not in plan


def test_long_documents_keep_their_lines(spark):
    text = "\n".join(f"line number {k}" for k in range(500))
    rows = [(1, text, "en", "s", 0), (2, "\n".join(f"line number {k}" for k in range(0, 500, 2)) + "\nonly here and now", "en", "s", 0)]
    got = {r.doc_id: r for r in line_dedup.dedup_lines(frame(spark, rows)).collect()}
    assert (got[1].n_dropped, got[2].n_dropped, got[2].kept) == (0, 250, "only here and now")


# op 5 ----------------------------------------------------------------------------------------------------------------


def targets_by_hand(sizes):
    names = sorted(sizes, key=lambda s: (s is None, s or ""))
    weight = {s: (5, 2, 1)[k % 3] for k, s in enumerate(names)}
    left, free, out = 1.5 * sum(sizes.values()), set(names), {}
    while True:
        level = left / sum(weight[s] for s in free) if free else 0
        full = {s for s in free if level * weight[s] > 2 * sizes[s]}
        if not full:
            return out | {s: level * weight[s] for s in free}
        for s in full:
            out[s] = 2 * sizes[s]
            left -= out[s]
        free -= full


@pytest.mark.parametrize("block", [mixing.BLOCK, 3])
def test_mixing(spark, awkward, block):
    docs = clashing(frame(spark, awkward))
    got = mixing.mix(docs, block=block).collect()
    words = sorted(len(WORD.findall(t or "")) for _, t, *_ in awkward)
    assert sorted(r["size"] for r in got) == words
    by = collections.defaultdict(int)
    for _, t, _, s, _ in awkward:
        by[s] += len(WORD.findall(t or ""))
    want = targets_by_hand(dict(by))
    taken = collections.defaultdict(int)
    for r in got:
        assert r.target == pytest.approx(want[r.source]) and r.source_size == by[r.source] and 0 <= r.taken <= 2 * r["size"]
        taken[r.source] += r.taken
    for s, n in taken.items():
        assert abs(n - want[s]) <= 1 + sum(r.source == s for r in got)
    again = mixing.mix(docs.repartition(5), block=block).collect()
    key = lambda rows: sorted((str(r.doc_id), r["size"], r.taken) for r in rows)
    assert key(again) == key(got)


def test_pivotal_steps_keep_words_and_expectations():
    rng = np.random.default_rng(0)
    size, p = np.array([5, 9, 2, 14, 7, 3]), 0.37
    total = np.zeros(6)
    for _ in range(4000):
        share = np.full(6, p)
        k = mixing.pivot(size, share, rng.random(6))
        assert (share * size).sum() == pytest.approx(p * size.sum())
        assert sum(1e-9 < x < 1 - 1e-9 for x in share) <= 1 and (k is None or 0 < share[k] < 1)
        total += share
    assert np.allclose(total / 4000, p, atol=0.03)


def test_mixed_documents_take_whole_texts(spark, awkward):
    docs = frame(spark, awkward)
    out = mixing.mixed_documents(docs)
    assert out.columns == [*docs.columns, "copy"] and out.agg(F.max("copy")).first()[0] <= 2
    assert mixing.mix(frame(spark, [])).count() == 0 and mixing.mixed_documents(frame(spark, [])).count() == 0


# op 6 ----------------------------------------------------------------------------------------------------------------

PAGE = """<!DOCTYPE html><html><head><title>T &amp; x</title><style>p{}</style><script>var a="</p><p>no</p>";</script></head><body><header><a href=/>Home</a></header>
<nav><ul><li><a href="/a">Menu one</a></li><li><a href="/b">Menu two</a></li></ul></nav><!-- <p>hidden</p> --><div class="cookie">We use cookies, accept?</div>
<article><h1>Title &eacute;&#33;</h1><p>First   <b>bold</b>\n paragraph&nbsp;of text, which goes on for a while.<p>Second one<br>goes on &lt;here&gt;.</p><div class="ad">Buy now</div></article>
<form class="search"><label>Find</label><button>Go</button></form><div class="comments"><div class="comment"><span>bob</span><p>I disagree with this article a lot.</p></div></div><footer>&copy; 2024 someone</footer></body></html>"""


def test_html_blocks_and_text():
    found = html_extract.blocks(PAGE)
    assert [b.text for b in found if "article" in b.path] == ["Title é!", "First bold paragraph of text, which goes on for a while.", "Second one goes on <here>.", "Buy now"]
    assert html_extract.main_text(html_extract.train(), [PAGE, ""]) == ["Title é!\nFirst bold paragraph of text, which goes on for a while.\nSecond one goes on <here>.", ""]
    for odd in ("plain", "<", "<p", "<<p>>a</p", "<script>x", "<!-- open", "</p></div>text", '<a href="x>y</a>', "<p>" * 500 + "deep", "&#xZZ; &bogus; &#0;"):
        html_extract.main_text(html_extract.train(), [odd])


def test_html_gradient():
    rng = np.random.default_rng(0)
    w = html_extract.new_weights(rng)
    pages = [rng.normal(size=(n, html_extract.WIDTH)) for n in (3, 5)]
    labels = [rng.integers(0, 2, n).astype(float) for n in (3, 5)]
    _, grad = html_extract.gradient(w, pages, labels)
    for name in w:
        at = tuple(0 for _ in w[name].shape)
        old = w[name][at]
        w[name][at] = old + 1e-5
        up = html_extract.gradient(w, pages, labels)[0]
        w[name][at] = old - 1e-5
        down = html_extract.gradient(w, pages, labels)[0]
        w[name][at] = old
        assert grad[name][at] == pytest.approx((up - down) / 2e-5, abs=1e-6)


def test_html_held_out_pages_and_given_ones(spark):
    rng, hit, n = np.random.default_rng(99), 0, 0
    w = html_extract.train()
    for _ in range(150):
        page, labels = html_extract.training_page(rng)
        got = html_extract.chances(w, [html_extract.vectors(html_extract.blocks(page))])[0] >= 0.5
        hit, n = hit + (got == np.array(labels, bool)).sum(), n + len(labels)
    assert hit / n > 0.985
    for r in html_extract.extract(spark.read.parquet(f"{SF}/pages.parquet")).join(spark.read.parquet(f"{SF}/pages.parquet").select("page_id", "html"), "page_id").collect():
        assert r.text == "\n".join(b.text for b in html_extract.blocks(r.html) if any(p.split()[0] == "article" for p in b.path)) and r.n_chars == len(r.text)


def strange_page(rng, labelled):
    """A page made by other rules than the training pages: real words, names that they never use, tables and links as
    furniture, nested wrappers. labelled: whether the article's element says what it is; otherwise it is a bare div."""
    pool = "time year people way day man thing woman life child world school state family student group country problem hand part place case week company system program question work government number night point home water room mother area money story fact month lot right study book eye job word business issue side kind head house service friend father power hour game line end member law car city".split()
    text = lambda n: " ".join(pool[k] for k in rng.integers(0, len(pool), n)).capitalize() + "."
    name = lambda: f'class="{rng.choice(["td", "mw", "xq", "css"])}-{rng.integers(1000)}"'
    out, labels = [f"<html><head><title>{text(4)}</title></head><body {name()}><div {name()}>"], [0]

    def put(html, n, label):
        out.append(html)
        labels.extend([label] * n)

    links = lambda n: "".join(f'<td><a href="/{k}">{text(2)[:-1]}</a></td>' for k in range(n))
    k = int(rng.integers(3, 8))
    put(f'<div class="top-menu"><table><tr>{links(k)}</tr></table></div>', k, 0)
    if rng.random() < 0.5:
        put(f'<div class="gdpr-notice">{text(20)}</div>', 1, 0)
    main = ["<article>", '<div class="post-content">', '<main class="page">', '<section class="article-text">'][rng.integers(4)] if labelled else "<div>"
    out.append(f"<div {name()}>{main}")
    put(f"<h1>{text(6)[:-1]}</h1>", 1, 1)
    for _ in range(int(rng.integers(3, 15))):
        put(f"<p>{text(int(rng.integers(10, 90)))}</p>", 1, 1)
        if rng.random() < 0.1:
            put(f'<div class="advert">{text(8)}</div>', 1, 0)
        if rng.random() < 0.1:
            put(f"<h3>{text(3)[:-1]}</h3>", 1, 1)
    out.append("</" + main[1:].split()[0].strip(">") + "></div>")
    if rng.random() < 0.6:
        k = int(rng.integers(2, 6))
        put('<div class="sidebar-box"><ul>' + "".join(f'<li><a href="#">{text(4)[:-1]}</a></li>' for _ in range(k)) + "</ul></div>", k, 0)
    if rng.random() < 0.5:
        k = int(rng.integers(1, 5))
        put('<div class="comments-area">' + "".join(f'<div class="comment-item"><b>{text(1)[:-1]}</b><p>{text(15)}</p></div>' for _ in range(k)) + "</div>", 2 * k, 0)
    put(f'<div class="site-footer">&copy; {text(5)}</div></div></body></html>', 1, 0)
    return "".join(out), labels


@pytest.mark.parametrize("labelled, least", [(True, 0.95), (False, 0.8)])
def test_html_pages_made_by_other_rules(labelled, least):
    rng, w, hit, n = np.random.default_rng(7), html_extract.train(), 0, 0
    for _ in range(200):
        page, labels = strange_page(rng, labelled)
        got = html_extract.chances(w, [html_extract.vectors(html_extract.blocks(page))])[0] >= 0.5
        hit, n = hit + (got == np.array(labels, bool)).sum(), n + len(labels)
    print("pages by other rules", labelled, hit / n)
    assert hit / n > least


def test_html_loses_no_text():
    text = lambda page: [b.text for b in html_extract.blocks(page)]
    for gap in ('<svg class="i"/>', "<iframe src=x>", "<textarea>", "<object>", "<noscript>", "<template>", "<math/>", "<svg>"):
        assert text(f"<article><p>aaa one</p>{gap}<p>bbb two</p></article>") == ["aaa one", "bbb two"]
    assert text("<p>sum <math><mi>x</mi><mo>=</mo><annotation>x</annotation></math> <svg><title>t</title><text>lab</text></svg> <object>other</object> end") == ["sum x= lab other end"]
    assert text('<p class=x">aaa</p><p a="b>c">ddd</p><p q="unclosed>eee</p>') == ["aaa", "ddd", "eee"]
    assert text("a < b &amp; c <d") == ["a < b & c <d"] and text("<!-->x<!-- y -->z<!-- open") == ["xz"]
    assert text("<svg><p>one</svg><p>two") == ["one", "two"] and text("<script>no</script>yes<style>no") == ["yes"]


def test_html_parsing_takes_time_in_proportion():
    import time

    for page in ('<a "' * 250_000, "<span>x" * 150_000, "<div>x" * 100_000, "<svg>" + "<desc>x" * 150_000, "<" * 1_000_000, '<a b="' * 170_000 + ">", '<a b=">" ' * 120_000, "<span>" * 80_000 + "<hr>x" * 100_000, "<!--" * 250_000, "<li>" * 250_000):
        began = time.process_time()
        html_extract.blocks(page)
        assert time.process_time() - began < 10, page[:20]
    page = "<article>" + "<p>word one two</p>" * 60_000 + "</article>"
    assert len(html_extract.projected(html_extract.train(), [html_extract.blocks(page)])[0]) == 60_000


def test_html_awkward_rows(spark):
    rows = spark.createDataFrame([(1, None, None), (None, "u", ""), (2, "u", PAGE), (2, "u", PAGE)], "page_id long, url string, html string")
    got = html_extract.extract(clashing(rows)).collect()
    assert len(got) == 4 and sorted(r.n_chars for r in got)[:2] == [0, 0]


# op 7 ----------------------------------------------------------------------------------------------------------------


def test_warc_round_trip(spark):
    big, nasty = "é" * 40_000 + "end", "\r\n\r\nWARC/1.1\r\nWARC-Type: response\r\n" * 60
    rows = [(1, "http://a/\n x", big), (2, None, big), (3, "u", nasty), (4, "u", "small"), (5, "u", "small"), (6, "u", None), (7, "u", ""), (8, "u", "a" * 1000), (9, "u", "a" * 1000), (9, "u", "a" * 1000), (None, "u", "a" * 1000), (None, "u", "b" * 2000), (10, "u", "\r\n" * 30_000), (11, "u", big + "x"), (11, "u", big + "x")]
    got = warc.round_trip(clashing(spark.createDataFrame(rows, "page_id long, url string, html string"))).collect()
    assert not any(r.problem for r in got)
    chosen = {}
    for i, _, h in rows:
        if i is not None and len((h or "").encode()) >= 1000:
            chosen[h] = max(chosen.get(h, i), i)
    want = []
    for i, _, h in rows:
        raw = (h or "").encode()
        first = chosen.get(h)
        again = first is not None and first != i
        want.append((str(i), len(raw), hashlib.sha1(raw).hexdigest(), "revisit" if again else "response", str(first if again else None)))
    assert sorted((str(r.page_id), r.payload_bytes, r.payload_digest, r.record_type, str(r.refers_to)) for r in got) == sorted(want)
    assert warc.round_trip(spark.createDataFrame([], "page_id long, url string, html string")).count() == 0


def test_warc_loses_no_page(spark):
    """As many pages as it takes for records to end at every place of a read buffer, ending in every awkward way."""
    ends = ["", "\r", "\n", "\r\n", "\r\n\r\n", "\r\n\r\n\r\n", "W", "WARC/", "WARC/1.1", "WARC/1.1\r\n", "\r\n\r\nWARC/1.1\r\n", "0\r\n\r\n", "é"]
    n = 75_000
    page = F.concat(F.repeat(F.lit("x"), (F.col("id") * 7919 % 700).cast("int")), F.element_at(F.array(*map(F.lit, ends)), (F.col("id") % len(ends) + 1).cast("int")))
    url = F.when(F.col("id") % 3 == 0, F.lit("http://a/WARC/1.1")).otherwise(F.lit("http://a/b"))
    pages = spark.range(0, n, 1, 4).select(F.col("id").alias("page_id"), url.alias("url"), page.alias("html"))
    got = warc.round_trip(pages)
    assert got.count() == n and got.where("problem is not null").count() == 0
    same = got.join(pages.select("page_id", F.sha1(F.col("html").cast("binary")).alias("want"), F.col("url").alias("want_url")), "page_id")
    assert same.where("payload_digest = want and url = want_url").count() == n


def test_surplus_bytes_are_a_problem(spark, tmp_path):
    good = warc.page_records(1, "u", b"a page", hashlib.sha1(b"a page").hexdigest(), None)[0]
    (tmp_path / "a.warc").write_bytes(good + warc.END + good + b"surplus" + warc.END + good[:-3] + warc.END)
    got = [r.problem for r in warc.read_pages(spark, str(tmp_path / "a.warc")).collect()]
    assert len(got) == 3 and sum(p is None for p in got) == 1


def test_warc_archives_are_readable_by_length(spark, tmp_path):
    pages = spark.read.parquet(f"{SF}/pages.parquet")
    warc.write_pages(pages, str(tmp_path / "w"), segment=4096)
    whole, pieces = {}, collections.defaultdict(list)
    for p in (tmp_path / "w").glob("*.gz"):
        for f, block in warc.parse_archive(p.read_bytes()):
            assert len(block) == int(f["content-length"])
            if n := f.get("warc-segment-number"):
                pieces[f.get("warc-segment-origin-id", f["warc-record-id"])].append((int(n), int(f["warc-segment-total-length"]) if "warc-segment-total-length" in f else None, block))
            elif f["warc-type"] == "response":
                whole[f["warc-record-id"]] = warc.payload_of(f, block)
    for k, v in pieces.items():
        assert len(v) > 1
        whole[k] = warc.payload_of({}, warc.assemble(v))
    assert {hashlib.sha1(v).hexdigest() for v in whole.values()} == {hashlib.sha1((r.html or "").encode()).hexdigest() for r in pages.collect()}


def test_broken_archives_are_reported():
    assert warc.dechunk(warc.chunked(b"x" * 50_000)) == b"x" * 50_000
    for bad in ([(1, None, b"a"), (3, 2, b"b")], [(1, None, b"a"), (2, 5, b"b")], [(2, 1, b"a")]):
        with pytest.raises(ValueError):
            warc.assemble(bad)
    for bad in (b"5\r\nabc", b"zz\r\n", b""):
        with pytest.raises(ValueError):
            warc.dechunk(bad)
    assert b"WARC/1.1" not in warc.chunked(b"WARC/1.1WARC/1.1")


# op 8 ----------------------------------------------------------------------------------------------------------------


def test_language_held_out_accuracy(spark):
    docs = spark.read.parquet("/root/testdata/sf0.01/documents.parquet")
    got = langid.identify(docs, langid.learn(docs)).where("lang is not null").collect()
    held = [r for r in got if zlib.crc32(str(r.doc_id).encode()) % 5 == 0]
    assert len(held) > 100 and np.mean([r.lang == r.lang_pred for r in held]) > 0.97 and all(0 <= r.score <= 1 for r in got)


def test_language_awkward_rows(spark, awkward):
    docs = clashing(frame(spark, awkward))
    got = langid.identify(docs, langid.learn(docs)).collect()
    assert len(got) == len(awkward)
    for r in got:
        letters = any(c.isalpha() for c in r.text or "")
        assert (r.lang_pred == "und") == (not letters) and (letters or r.score == 0)
    none = frame(spark, [(1, "word", None, "s", 1)])
    assert [r.lang_pred for r in langid.identify(none, langid.learn(none)).collect()] == ["und"]
    held = frame(spark, [(k, "words here", "xx", "s", 1) for k in range(200) if zlib.crc32(str(k).encode()) % 5 == 0])
    assert langid.learn(held) is None


@pytest.mark.parametrize("label", [None, "und"])
def test_language_stage_keeps_texts_with_letters(spark, awkward, label):
    import corpus_pipeline as P

    rows = [(i, t, label, s, n) for i, t, _, s, n in awkward] + [(100 + k, f"words here {k}", label, "s", 1) for k in range(20)]
    kept = P.language(spark, clashing(frame(spark, rows)), "").collect()
    assert sorted(r.text for r in kept) == sorted(t for _, t, *_ in rows if any(c.isalpha() for c in t or ""))


def test_equal_ids_do_not_swell_the_sample(spark, monkeypatch):
    ids = [k for k in range(400) if zlib.crc32(str(k).encode()) % 5]
    rows = [(ids[0], f"the same words {k}", "en", "s", 1) for k in range(3000)] + [(k, f"other words here {k}", "en", "s", 1) for k in ids[1:]] + [(k, f"des mots ici {k}", "fr", "s", 1) for k in ids]
    seen = []
    monkeypatch.setattr(langid, "fit", lambda x, lang: seen.append(lang))
    langid.learn(frame(spark, rows), sample=50)
    assert collections.Counter(seen[0]) == {"en": 50, "fr": 50}


def test_machines_separate_and_votes_decide():
    rng = np.random.default_rng(0)
    x = np.abs(rng.normal(size=(300, 40)))
    lang = [["en", "de", "nl", "fr"][k % 4] for k in range(300)]
    for k in range(300):
        x[k, (k % 4) * 10 : (k % 4) * 10 + 10] += 4
    x /= np.linalg.norm(x, axis=1, keepdims=True)
    model = langid.fit(np.hstack([x, np.ones((300, 1))]), lang)
    assert model.families == ["germanic", "romance"] and len(model.pairs["germanic"][0]) == 3
    assert langid.predict(model, np.hstack([x, np.ones((300, 1))]))[0] == lang


# op 9 ----------------------------------------------------------------------------------------------------------------


def smith_waterman(a, b):
    h = np.zeros((len(a) + 1, len(b) + 1), int)
    for i in range(1, len(a) + 1):
        for j in range(1, len(b) + 1):
            h[i, j] = max(0, h[i - 1, j - 1] + (2 if a[i - 1] == b[j - 1] else -1), h[i - 1, j] - 1, h[i, j - 1] - 1)
    return h.max()


def test_alignment_equals_the_plain_table():
    rng = np.random.default_rng(0)
    items = [rng.integers(1, 6, n).astype(np.uint64) for n in (5, 12, 30, 1)]
    windows = [rng.integers(1, 6, n).astype(np.uint64) for n in (20, 9, 41, 1)]
    assert decontam.align(items, windows)[0].tolist() == [smith_waterman(a, b) for a, b in zip(items, windows, strict=True)]


def test_decontamination(spark, awkward):
    rng = random.Random(7)
    words = [f"{a}{b}" for a in "bcdfghklmnprst" for b in ("an", "el", "ir", "os", "um")]
    items = [" ".join(rng.choice(words) for _ in range(n)) for n in (40, 25, 8, 3)] + ["été über école Garçon ñandú"]
    filler = lambda n: " ".join(rng.choice(words) for _ in range(n))
    edited = " ".join(rng.choice(words) if k % 6 == 5 else w.upper() + "," for k, w in enumerate(items[0].split()))
    rows = [(1, filler(50) + " " + items[0] + " " + filler(60), "en", "s", 0), (2, edited, "en", "s", 0), (3, filler(300), "en", "s", 0), (4, items[1], "en", "s", 0), (5, filler(20) + ". " + items[2], "en", "s", 0), (6, items[3], "en", "s", 0), (16, "x " + items[4].upper() + " y", "en", "s", 0), (7, " ".join(items[1].split()[:9]) + " " + filler(40), "en", "s", 0)]
    rows += [(8, "Grüße ÉTÉ " + items[3] + " élan", "en", "s", 0)]
    rows += [(50 + k, items[1] + " " + filler(30), "en", "s", 0) for k in range(60)]  # a leak that is everywhere
    bench = spark.createDataFrame([(k, t) for k, t in enumerate(items)] + [(None, filler(30)), (9, None), (10, "")], "item_id long, text string")
    for per_block in (decontam.ITEMS_PER_BLOCK, 2):
        got = {r.doc_id: r for r in decontam.decontaminate(frame(spark, rows), bench, per_block).collect()}
        bad = {i: got[i].item_id for i in got if got[i].contaminated}
        assert bad == {1: 0, 2: 0, 4: 1, 5: 2, 6: 3, 16: 4} | {50 + k: 1 for k in range(60)}  # 6 is a short item as a line; in 8 it stands in a sentence
        assert got[4].score == got[6].score == 1
    odd = clashing(frame(spark, awkward))
    out = decontam.decontaminate(odd, bench)
    assert out.count() == len(awkward) and out.where("contaminated").count() == 0
    assert decontam.clean_documents(odd, bench).columns == odd.columns
    none = spark.createDataFrame([], "item_id long, text string")
    assert decontam.decontaminate(odd, none).where("contaminated").count() == 0 and decontam.decontaminate(frame(spark, []), bench).count() == 0


def edited_copy(rng, words, pool, rate):
    """A copy with about `rate` of its words changed, dropped or followed by another."""
    out = []
    for w in words:
        if rng.random() >= rate:
            out.append(w)
        else:
            out += rng.choice([[rng.choice(pool)], [], [w, rng.choice(pool)]])
    return out


@pytest.mark.parametrize("rate", [0, 0.05, 0.1, 0.2, 0.3])
def test_decisions_against_aligning_everything(spark, rate):
    """Every document is aligned with every item as a whole: nothing else is flagged, and of what that finds, nine tenths
    and more at every rate of edits."""
    rng = random.Random(11)
    pool = [f"{a}{b}{c}" for a in "bcdfgh" for b in ("an", "el", "ir", "os") for c in "klmnrst"]
    items = [[rng.choice(pool) for _ in range(rng.randrange(8, 40))] for _ in range(60)]
    filler = lambda n: [rng.choice(pool) for _ in range(n)]
    docs = [filler(rng.randrange(60)) + edited_copy(rng, rng.choice(items), pool, rate) + filler(rng.randrange(60)) for _ in range(150)] + [filler(120) for _ in range(50)]
    number = {w: np.uint64(k + 2) for k, w in enumerate(pool)}
    coded = lambda ws: np.array([number[w] for w in ws], np.uint64)
    best = np.array([decontam.align([coded(i) for i in items], [coded(d)] * len(items))[0] / (2 * np.array(list(map(len, items)))) if d else np.zeros(len(items)) for d in docs])
    want = best.max(axis=1) >= decontam.THRESHOLD
    bench = spark.createDataFrame([(k, " ".join(w)) for k, w in enumerate(items)], "item_id long, text string")
    got = {r.doc_id: r for r in decontam.decontaminate(frame(spark, [(k, " ".join(d), "en", "s", 0) for k, d in enumerate(docs)]), bench).collect()}
    flagged = np.array([got[k].contaminated for k in range(len(docs))])
    assert not (flagged & ~want).any() and (flagged & want).sum() >= 0.9 * want.sum() and want.sum() >= 100
    for k in np.flatnonzero(flagged):
        assert got[k].score <= best[k, got[k].item_id] + 1e-12
    print(rate, int(want.sum()), int(flagged.sum()))


def test_templates_do_not_multiply_candidates(spark):
    rng = random.Random(5)
    own = [f"{a}{b}{k}" for a in "bcdf" for b in ("an", "el") for k in range(40)]
    template = "please choose the one right answer to the question that follows here".split()
    texts = [" ".join(template + [rng.choice(own) for _ in range(10 + k % 3)]) for k in range(600)] + ["the very same item stands here six hundred times over"] * 2
    index = decontam.index_items(list(range(602)), texts)
    assert np.diff(index.at).max() <= decontam.ITEMS_PER_SEED
    filler = " ".join(rng.choice(own) for _ in range(30))
    edited = texts[77].split()
    edited[3] = edited[15] = "other"
    rows = [(1, f"{filler} {texts[500]} {filler}", "en", "s", 0), (2, " ".join(edited), "en", "s", 0), (3, filler, "en", "s", 0), (4, " ".join(template), "en", "s", 0), (5, texts[600], "en", "s", 0), (6, " ".join(template[:6]) + " " + filler, "en", "s", 0)]
    got = {r.doc_id: r for r in decontam.decontaminate(frame(spark, rows), spark.createDataFrame(list(enumerate(texts)), "item_id long, text string")).collect()}
    assert (got[1].item_id, got[1].score, got[2].item_id) == (500, 1, 77) and got[2].contaminated
    assert got[4].contaminated and got[4].item_id == 0  # the template alone is over half of the shortest items
    assert got[5].item_id == 600 and not got[3].contaminated and not got[6].contaminated


def test_short_items_are_matched_by_line(spark):
    bench = spark.createDataFrame([(4, "Who is it?"), (2, "who is IT"), (7, "yes"), (8, "?!")], "item_id long, text string")
    rows = [(1, "Q:\nWho is it\nme", "en", "s", 0), (2, "I know who is it that came", "en", "s", 0), (3, "yes", "en", "s", 0), (5, "yes yes", "en", "s", 0), (6, None, "en", "s", 0)]
    got = {r.doc_id: (r.contaminated, r.item_id) for r in decontam.decontaminate(frame(spark, rows), bench).collect()}
    assert got == {1: (True, 2), 2: (False, None), 3: (True, 7), 5: (False, None), 6: (False, None)}


def test_words_of_long_texts_are_hashed_in_pieces():
    from cutlearn.llm import textblocks as tb

    rng = np.random.default_rng(0)
    data = rng.choice(np.frombuffer(b"ab \n", np.uint8), 5000)
    data[1000:1900] = ord("a")
    s, e, _ = tb.words_of(data, np.array([0, 5000]))
    assert (tb.hashes_of(data, s, e, 300) == tb.RangeHash(data).of(s, e)).all()


def test_leaks_in_the_given_documents(spark):
    docs, bench = (spark.read.parquet(f"/root/testdata/sf0.01/{t}.parquet") for t in ("documents", "benchmark"))
    plain = lambda t: " ".join(t.lower().split())
    items = [plain(r.text) for r in bench.collect()]
    want = {r.doc_id for r in docs.collect() if any(i in plain(r.text) for i in items)}
    got = {r.doc_id for r in decontam.decontaminate(docs, bench).where("contaminated").collect()}
    assert want <= got and len(got - want) <= 2


@pytest.mark.parametrize("times", [11, 1000])
@pytest.mark.parametrize("whole", [0, 1])
def test_frequent_edited_and_shortened_leaks(spark, times, whole):
    items = [" ".join(f"w{k}x{j}" for j in range(30)) for k in range(2)]
    edited = " ".join("other" if j in (7, 15, 23) else w for j, w in enumerate(items[0].split()))
    shortened = " ".join(items[1].split()[:22])
    rows = [(k, f"{k} begins {(edited, shortened)[k % 2]} ends", "en", "s", 0) for k in range(2 * times)]
    rows += [(-1 - k, items[k], "en", "s", 0) for k in range(2 * whole)]  # a whole copy makes the missing seeds rare, not absent
    rows += [(10_000, " ".join(items[0].split()[:9]) + " and no more", "en", "s", 0)]
    bench = spark.createDataFrame(list(enumerate(items)), "item_id long, text string")
    got = {r.doc_id: r for r in decontam.decontaminate(frame(spark, rows), bench).collect()}
    assert {i for i, r in got.items() if not r.contaminated} == {10_000}
    assert got[0].item_id == 0 and got[1].item_id == 1 and abs(got[0].score - 0.85) < 1e-9 and abs(got[1].score - 44 / 60) < 1e-9


# op 10 ---------------------------------------------------------------------------------------------------------------

TURNS = "conv_id long, turn long, role string, text string"


def test_chat_round_trip(spark):
    rows = [(1, 0, "system", "be\nkind"), (1, 1, "user", Q.FORGED_TEXT), (1, 2, "assistant", " lead <|im_end|> \\<\\|im 你好😀é\n\n"), (1, 3, "assistant", "\nnext\t"), (2, 0, "user", None), (2, 1, "assistant", None), (2, 1, "assistant", ""), (3, None, None, "x<"), (3, 1, "assistant", "|y<|" * 3), (None, 0, "assistant", "null id"), (4, 0, "as|<|sistant", "z"), (5, 0, "assistant", "long " * 20_000)]
    df = clashing(spark.createDataFrame(rows, TURNS))
    every = chat.digests(chat.format_conversations(df)).collect()
    got = {r.conv_id: r for r in every}
    assert len(every) == len(got)
    by = collections.defaultdict(list)
    for c, t, r, x in rows:
        by[c].append(((t is not None, t or 0), r or "", x or ""))
    sha = lambda x: hashlib.sha256(x.encode()).hexdigest()
    assert set(got) == set(by)
    for c, turns in by.items():
        turns.sort()
        loss = "".join(x for _, r, x in turns if r == "assistant")
        g = got[c]
        assert (g.n_turns, g.turns_sha256, g.loss_chars, g.loss_sha256) == (len(turns), sha("".join(f"{r}\n{x}\n" for _, r, x in turns)), len(loss), sha(loss))
        assert g.formatted_chars == len(chat.render([(r, x) for _, r, x in turns]))
    assert chat.format_conversations(spark.createDataFrame([], TURNS)).count() == 0


def test_turns_without_conversation_stand_alone(spark):
    rows = [(None, k % 2, "assistant", f"text {k % 3}") for k in range(12)]
    got = chat.digests(chat.format_conversations(spark.createDataFrame(rows, TURNS))).collect()
    assert len(got) == 12 and all(r.conv_id is None and r.n_turns == 1 and r.loss_chars == 6 for r in got)
    with pytest.raises(FileNotFoundError, match="format_conversations"):
        chat.tokenizer("/nowhere/vocabulary.json")


def test_escapes_undo_and_hide_marks():
    rng = random.Random(0)
    for _ in range(3000):
        t = "".join(rng.choice(["<", "|", "\\", "im_end", "|>", "a", chat.OPEN, chat.CLOSE]) for _ in range(rng.randrange(9)))
        assert chat.unescape(chat.escape(t)) == t
        assert not any(m in chat.escape(t) for m in (chat.OPEN, chat.MIDDLE, chat.CLOSE))


def test_masks_follow_tokens():
    s, e = np.array([0, 3, 5, 9]), np.array([3, 5, 9, 12])
    assert chat.token_mask(s, e, np.array([4, 9]), np.array([6, 10]))[0].tolist() == [False, True, True, True]
    assert not chat.token_mask(s, e, np.zeros(0, int), np.zeros(0, int))[0].any()


# queries and pipeline -------------------------------------------------------------------------------------------------


@pytest.mark.parametrize("name", sorted(Q.ORACLE_SQL))
def test_query_equals_sql(spark, duck, name):
    assert same_rows(Q.QUERIES[name](spark, SF), duck, Q.ORACLE_SQL[name])


def rows_of(spark, table):
    return [tuple(r) for r in spark.read.parquet(f"{SF}/{table}.parquet").collect()]


def test_registered_queries_equal_brute_force(spark):
    """The queries without SQL over the smallest tables, as they are registered."""
    docs, run = rows_of(spark, "documents"), lambda name: Q.QUERIES[name](spark, SF).collect()
    assert sorted((tuple(r)[:5] for r in run("op1_suffix_dedup")), key=str) == removed_by_brute_force(docs)
    got = run("op2_quality_rules")
    names = ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words")
    assert sorted((r.doc_id, *(r[c] for c in names)) for r in got) == sorted((i, *base_measures(t)) for i, t, *_ in docs)
    assert sorted((str(r.doc_id), r.fingerprint, str(r.component_id)) for r in run("op3_simhash")) == components_by_brute_force(docs)
    by, taken = collections.defaultdict(int), collections.defaultdict(int)
    for _, t, _, s, _ in docs:
        by[s] += len(WORD.findall(t or ""))
    want = targets_by_hand(dict(by))
    for r in run("op5_mixing"):
        assert r.target == pytest.approx(want[r.source]) and 0 <= r.taken <= 2 * r["size"]
        taken[r.source] += r.taken
    assert all(abs(n - want[s]) <= 1 for s, n in taken.items())
    got = run("op8_language_id")
    lang = {i: x for i, _, x, *_ in docs}
    held = [r for r in got if r.held_out and lang[r.doc_id]]
    assert len(got) == len(docs) and np.mean([r.lang_pred == lang[r.doc_id] for r in held]) > 0.9
    got = {r.doc_id for r in run("op9_decontamination") if r.contaminated}
    plain = lambda t: " ".join(re.findall(r"[^\W_]+", (t or "").lower()))
    items = [plain(x[1]) for x in rows_of(spark, "benchmark")]
    assert got >= {i for i, t, *_ in docs if any(x and f" {x} " in f" {plain(t)} " for x in items)}


def test_pipeline_stage_by_stage(spark, awkward, tmp_path):
    import corpus_pipeline as P

    bench = spark.createDataFrame([(1, "one two three four five six seven eight nine")], "item_id long, text string")
    bench.write.parquet(str(tmp_path / "benchmark.parquet"))
    rows = awkward + [(90, "well: one two three four five six seven eight nine", "en", "s1", 1)]
    docs, kept = clashing(frame(spark, rows)), None
    for name, stage in P.STAGES:
        stage(spark, docs, str(tmp_path)).write.parquet(str(tmp_path / name))
        out = spark.read.parquet(str(tmp_path / name))
        assert set(out.columns) - {"copy"} == set(docs.columns) - {"copy"}
        kept = out
        if name == "language_id":
            assert out.count() == sum(any(c.isalpha() for c in t or "") for _, t, *_ in rows)
        if name == "line_dedup":
            want = [x for x in lines_by_brute_force([r for r in rows if any(c.isalpha() for c in r[1] or "")])]
            assert sorted(r.text for r in out.collect()) == sorted(x[3] for x in want)
        if name == "decontamination":
            assert 90 not in {r.doc_id for r in out.collect()}
        docs = out
    assert kept.count() > 0
    empty = frame(spark, [])
    for _, stage in P.STAGES:
        assert stage(spark, empty, str(tmp_path)).count() == 0
