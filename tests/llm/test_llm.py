"""Each operator against brute force on small data with nulls, empty and long texts, ties, repeated rows, no rows and clashing columns."""

import hashlib
import math
import random
import re
import zlib
from collections import Counter
from types import SimpleNamespace

import numpy as np
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

from ontospark.llm import chat, components, decontaminate, jaccard_join, langid, line_dedup, lm_score, packing, quality, queries, substring_dedup, topk
from ontospark.llm import pipeline as stages
from ontospark.llm._text import LOWER, grams, hashed_words, sliding_min, spans

WORD = re.compile(r"[^\x20\x09-\x0D]+")
DOC = "doc_id long, text string, bucket string, slice int, node long, removed string, doc long, body string, pos int, gone int, row int, q int"


def corpus(seed=0, n=60):
    rng = random.Random(seed)
    vocab = [f"w{i}" for i in range(400)] + ["Été", "don't", "x" * 300]
    base = [[rng.choice(vocab) for _ in range(rng.choice((1, 3, 25, 60, 150)))] for _ in range(n)]
    for i in range(0, n, 4):  # near and exact copies, shared passages
        j = rng.randrange(n)
        base[i] = list(base[j])
        if i % 8:
            base[i][rng.randrange(len(base[i]))] = "changed"
    passage = [rng.choice(vocab) for _ in range(30)]
    for i in range(0, n, 5):
        base[i] = base[i] + passage + ["tail", str(i)]
    out = [(i, re.sub(r" (w1\d )", r"\n\1", " ".join(w))) for i, w in enumerate(base)]
    return out + [(n, None), (n + 1, ""), (n + 2, " \n\t "), (n + 3, "a b\n" * 400), (n + 4, "a b\n" * 400), (5, out[5][1])]


def frame(spark, rows):
    return spark.createDataFrame([(d, t, *[None] * 10) for d, t in rows], DOC)


def words(t, lower=False):
    return WORD.findall((t or "").encode().translate(LOWER).decode() if lower else (t or ""))


def test_word_hashes_and_grams():
    raw = " Añb\tc  d\x0b e\x1cf ".encode()
    b, s, e = spans(raw)
    assert [raw[i:j].decode() for i, j in zip(s, e, strict=True)] == WORD.findall(raw.decode())
    h = hashed_words(b"a b c a b c a")
    for n in (1, 2, 3, 5, 7):
        g = grams(h, n)
        assert len(g) == 8 - n and all((g[i] == g[j]) == (i % 3 == j % 3) for i in range(len(g)) for j in range(len(g)))
    x = np.array([5, 3, 4, 1, 2], np.uint64)
    assert sliding_min(x, 3).tolist() == [3, 1, 1]
    assert (hashed_words(b"ab " * 2_000_000) == hashed_words(b"ab")[0]).all()


@pytest.mark.parametrize("group", [substring_dedup.GROUP, 1])
def test_substring_dedup(spark, group, monkeypatch):
    monkeypatch.setattr(substring_dedup, "GROUP", group)
    rows = corpus()
    seen, want = {}, {}
    for d, t in rows:
        w = words(t)
        for p in range(len(w) - 19):
            k = tuple(w[p : p + 20])
            seen[k] = min(seen.get(k, (d, p)), (d, p))
    for d, t in rows:
        w = words(t)
        gone = {q for p in range(len(w) - 19) if seen[tuple(w[p : p + 20])] < (d, p) for q in range(p, p + 20)}
        kept = " ".join(x for i, x in enumerate(w) if i not in gone)
        want[d] = (len(w), len(gone), hashlib.sha256(kept.encode()).hexdigest(), kept)
    got = substring_dedup.drop_repeats(frame(spark, rows), digest=True).collect()
    assert len(got) == len(rows) and all((r.n_words, r.n_removed, r.kept_sha256) == want[r.doc_id][:3] for r in got)
    assert sum(r.n_removed for r in got) > 500
    texts = substring_dedup.drop_repeats(frame(spark, rows)).collect()
    assert all(r.text == want[r.doc_id][3] and sum(x.end - x.start for x in r.removed) == r.n_removed for r in texts)
    assert substring_dedup.drop_repeats(frame(spark, [])).count() == 0


def test_groups_of_a_prefix_are_bounded():
    rng = random.Random(2)
    # an 8-word run that all documents hold, each time with other words around it, with so small a hash that it is the anchor
    often = min((" ".join(f"o{k}_{i}" for i in range(8)) for k in range(300)), key=lambda t: int(grams(hashed_words(t.encode()), 8)[0]))
    docs = [(i, None, hashed_words(f"{' '.join(f'x{rng.randrange(10**6)}' for _ in range(20))} {often} {' '.join(f'y{rng.randrange(10**6)}' for _ in range(20))}".encode())) for i in range(400)]
    sent = [substring_dedup._send_prefixes(20, 8, 1)(pa.table({"slice": [s] * 100, "body": [b""] * 100})) for s in range(2)]
    assert all(t.num_rows == 0 for t in sent)
    for group, bounded in ((1000, True), (10**9, False)):
        v = np.unique(np.concatenate([substring_dedup._anchors(h, 20, 8)[0] for *_, h in docs]))
        n = Counter(x for *_, h in docs for x in substring_dedup._anchors(h, 20, 8)[0].tolist())
        x = np.zeros(len(v), substring_dedup._OPEN)
        x["v"], x["n"] = v, [n[int(i)] for i in v]
        blob = pa.RecordBatch.from_pydict({"slice": [0], "blob": [substring_dedup._pack(x)]})
        (back,) = [b for b in substring_dedup._open_prefixes(group)([blob])]
        leaves = substring_dedup._leaves(docs, substring_dedup._opened(back.column("blob").to_pylist()), 20, 8)
        largest = max(Counter(leaves["key"].tolist()).values())
        assert (largest <= group) if bounded else largest > 1000
    assert (np.diff(leaves["h"].astype(float)) >= 0).all()  # leaves are sorted by label, nodes are runs


def test_told_nodes_are_found_by_both_labels():
    rng = np.random.default_rng(1)
    pairs = sorted({(int(a), int(b)) for a, b in rng.integers(0, 12, (90, 2))})  # many nodes share a first label
    head = np.array(pairs, dtype=substring_dedup._NODE)
    told = head[rng.random(len(head)) < 0.4]
    more = np.array([(a, 99) for a in range(12)], dtype=substring_dedup._NODE)
    got = substring_dedup._among(head, rng.permutation(np.concatenate([told, told, more])))
    assert [p for p, x in zip(pairs, got, strict=True) if x] == [tuple(map(int, x)) for x in told]


def test_blobs_are_packed_by_field():
    x = np.zeros(5, substring_dedup._LEAF)
    x["h"], x["g"], x["doc"], x["pos"] = np.arange(5).astype(np.uint64) + np.uint64(2**63), np.arange(5), -np.arange(5), 7
    assert (substring_dedup._unpack(substring_dedup._pack(x), substring_dedup._LEAF) == x).all()


def test_line_dedup(spark):
    rows = corpus()
    lines = {d: (t.split("\n") if t is not None else []) for d, t in rows}
    seen = {}
    for d, ls in sorted(lines.items()):
        for p in range(len(ls) - 2):
            seen.setdefault(tuple(ls[p : p + 3]), (d, p))
    got = line_dedup.drop_repeated_lines(frame(spark, rows)).collect()
    assert len(got) == len(rows) and got[0].asDict().keys() >= {"bucket", "gone", "row"}
    for r in got:
        ls = lines[r.doc_id]
        gone = {q for p in range(len(ls) - 2) if ls[p].strip(" ") and seen[tuple(ls[p : p + 3])] < (r.doc_id, p) for q in range(p, p + 3)}
        assert (r._lines, r._removed) == (len(ls), len(gone))
        assert r.text == (None if not ls else "\n".join(x for i, x in enumerate(ls) if i not in gone))
    assert line_dedup.drop_repeated_lines(frame(spark, [])).count() == 0
    one = line_dedup.drop_repeated_lines(frame(spark, [(1, "a\nb"), (2, "b\nc"), (None, "b")]), run=1).collect()
    assert {r.doc_id: r.text for r in one} == {1: "a", 2: "c", None: "b"}


def test_maximal_runs_of_lines(spark):
    rng = random.Random(5)
    docs = {i: [f"l{rng.randrange(10**6)}" for _ in range(rng.randint(1, 12))] for i in range(12)}
    for i in range(3, 12):
        src = docs[rng.randrange(i)]
        lo = rng.randrange(len(src))
        docs[i] = docs[i] + src[lo : lo + rng.randint(1, 9)] + [f"end{i}"]
    docs[20] = ["same"] * 8
    rows = [(i, "\n".join(x)) for i, x in docs.items()]
    seen, later = {}, {}
    for i, x in sorted(docs.items()):
        for p in range(len(x) - 1):
            k = tuple(x[p : p + 2])
            if k in seen:
                later[i, p] = seen[k]
            seen.setdefault(k, (i, p))
    want = set()
    for (i, p), (j, q) in later.items():
        if later.get((i, p - 1)) != (j, q - 1):
            n = 0
            while later.get((i, p + n)) == (j, q + n):
                n += 1
            want.add((i, p, n + 1, j, q))
            assert docs[i][p : p + n + 1] == docs[j][q : q + n + 1]
    got = line_dedup.maximal_runs(frame(spark, rows + rows[:2]), run=2).collect()
    assert {(r.doc, r.start, r.length, r.source_doc, r.source_start) for r in got} == want and max(r.length for r in got) > 4
    assert line_dedup.maximal_runs(frame(spark, [])).count() == 0


def test_decontamination(spark):
    rng = random.Random(3)
    item = lambda n: " ".join(f"q{rng.randrange(10**6)}" for _ in range(n))
    items = [(1, item(40)), (2, item(8)), (3, "two Words"), (4, None), (5, ""), (1, item(12))]
    cut_item = items[0][1].split()
    cut_item[20] = "other"
    docs = [
        (1, "x " * 5000 + items[0][1].upper() + " y" * 5000), (2, "pre " + " ".join(cut_item) + " post"), (3, " ".join(cut_item[:20])), (4, f"a {items[1][1]} b {items[5][1]}"),
        (5, "these two words meet"), (6, None), (7, ""), (8, "clean text that holds nothing of them at all"), (8, items[1][1]), (None, items[1][1]),
    ]
    b = spark.createDataFrame([(i, t, 0, "z") for i, t in items], "item_id long, text string, len int, h string")
    got = {(r.doc_id, r.item_id): r.containment for r in decontaminate.leaks(frame(spark, docs), b).collect()}
    assert set(got) == {(1, 1), (2, 1), (4, 2), (4, 1), (5, 3), (8, 2), (None, 2)} and got[1, 1] == 1 and 0.8 <= got[2, 1] < 1
    left = decontaminate.drop_leaks(frame(spark, docs), b)
    assert {r.doc_id for r in left.collect()} == {3, 6, 7} and left.columns == frame(spark, docs).columns
    assert decontaminate.leaks(frame(spark, docs), b.limit(0)).count() == 0 and decontaminate.leaks(frame(spark, []), b).count() == 0


def test_jaccard_join(spark, monkeypatch):
    rows = corpus(1)
    sets = {}
    for d, t in rows:
        w = words(t, True)
        sets[d] = frozenset(tuple(w[i : i + 4]) for i in range(len(w) - 3)) if len(w) >= 4 else frozenset([tuple(w)] if w else [])
    root = {d: d for d in sets}

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    ids = sorted(sets)
    for a in ids:
        for b in ids:
            both = len(sets[a] & sets[b])
            if a < b and both and 100 * both >= 85 * len(sets[a] | sets[b]):
                x, y = find(a), find(b)
                root[max(x, y)] = min(x, y)
    got = jaccard_join.similar(frame(spark, rows), 4, 85).collect()
    assert len(got) == len(rows) and all((r.n_shingles, r.component_id) == (len(sets[r.doc_id]), find(r.doc_id)) for r in got)
    assert len({find(d) for d in ids}) < len(ids) - 5
    assert jaccard_join.similar(frame(spark, [])).count() == 0
    # few counters, and components far larger than a block and a slice
    for name, value in (("LEAST_BITS", 2), ("MOST_BITS", 2), ("BLOCK", 150), ("SLICE", 400)):
        monkeypatch.setattr(jaccard_join, name, value)
    calls = []
    monkeypatch.setattr(jaccard_join, "components", lambda e: calls.append(0) or components.components(e))
    again = jaccard_join.similar(frame(spark, rows), 4, 85).collect()
    assert sorted(map(str, again)) == sorted(map(str, got)) and len(calls) == 3


def test_words_are_asked_for_without_places():
    classes = lm_score.Classes([])
    bodies = [b"b a b c", None, b"", "Été x C".encode()]
    table = pa.table({"slice": [3] * 4, "body": pa.array(bodies, pa.binary())})
    asked = lm_score._ask(5, classes)(table)
    docs, at, held, _ = lm_score._slice_words(table, 5, classes)
    sent = np.concatenate([np.frombuffer(b, np.uint64) for b in asked.column("blob").to_pylist()])
    assert len(sent) == held == 5 and (sent[at] == np.concatenate(docs)).all()


def test_a_slice_of_a_large_component_takes_bounded_memory():
    import tracemalloc

    rng, n = np.random.default_rng(5), jaccard_join.SLICE // 1000
    texts = [" ".join(map(str, rng.integers(0, 10**6, 1004))).encode() for _ in range(n)]
    nodes = [jaccard_join.node_of(jaccard_join.shingle_set(t, 5)) for t in texts]
    group = pa.table({"slice": [0] * n, "root": [1] * n, "node": nodes, "body": texts})
    tracemalloc.start()
    tallied = jaccard_join._tally(5, 3)(group)
    peak = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    kept = sum(len(b) for b in tallied.column("blob").to_pylist()) // 12
    assert kept == len(np.unique(np.concatenate([jaccard_join.shingle_set(t, 5) for t in texts]))) and peak < 40 << 20


@pytest.mark.parametrize("m", jaccard_join.STEPS)
def test_prefixes_lose_no_link(m):
    rng = np.random.default_rng(m + 1)
    levels = rng.integers(0, 4, 1 << 16).astype(np.uint8)
    for n in (8, 13, 20, 40, 90, 300, 1500):
        for _ in range(60):
            a = np.unique(rng.integers(0, 2**63, n).astype(np.uint64))
            k = jaccard_join.most_different(2 * len(a), 85) // 2
            b = np.unique(np.concatenate([np.delete(a, rng.choice(len(a), k, replace=False)), rng.integers(0, 2**63, k).astype(np.uint64)]))
            common = len(np.intersect1d(a, b))
            p = jaccard_join.Prefixes(85, dict.fromkeys(range(80), m), levels)
            if 100 * common >= 85 * (len(a) + len(b) - common) and common < len(a):
                assert len(np.intersect1d(p.of(a), p.of(b)))


def unequal_links_kept(percent, steps):
    """Every size up to 60 and every size it can be linked with by adding shingles; the pairs seen."""
    rng = np.random.default_rng(7)
    levels, pairs = rng.integers(0, 4, 1 << 16).astype(np.uint8), 0
    for n in range(4, 61):
        for extra in range(1, n):
            if 100 * n < percent * (n + extra):
                break
            for _ in range(10):
                b = np.unique(rng.integers(0, 2**63, n + extra).astype(np.uint64))
                a = np.sort(rng.choice(b, n, replace=False))
                p = jaccard_join.Prefixes(percent, steps, levels)
                assert len(np.intersect1d(p.of(a), p.of(b))), (percent, n, extra)
                pairs += 1
    return pairs


@pytest.mark.parametrize("m", [None, *jaccard_join.STEPS])
def test_prefixes_lose_no_unequal_link(m):
    assert unequal_links_kept(85, {} if m is None else dict.fromkeys(range(80), m)) > 1000


def test_estimated_steps_lose_no_unequal_link():
    rng = np.random.default_rng(5)
    common = np.arange(1, 4, dtype=np.uint64)  # shared by all, so the shortest prefix and two matches cost much
    sample = [np.unique(np.concatenate([common, rng.integers(0, 2**63, n - 3).astype(np.uint64)])) for n in range(4, 61) for _ in range(8)]
    steps = jaccard_join.estimate_steps(sample, 10**9, 80)
    p = jaccard_join.Prefixes(80, {})
    assert set(steps.values()) - {jaccard_join.ONE} and all(p.bound(c) > 0 for c in steps)
    for s in (steps, *(dict.fromkeys(range(80), m) for m in jaccard_join.STEPS)):
        assert unequal_links_kept(80, s) > 1000


def test_short_texts_with_a_word_appended_are_linked(spark):
    rows = [(10 * n + k, " ".join(f"v{n}x{i}" for i in range(n + k))) for n in (9, 10, 11, 12, 13) for k in (0, 1)]
    got = {r.doc_id: r.component_id for r in jaccard_join.similar(frame(spark, rows), 4, 85).collect()}
    assert all(got[10 * n + 1] == 10 * n for n in (9, 10, 11, 12, 13))


def test_components_equal_brute_force(spark):
    rng = np.random.default_rng(3)
    ids = rng.integers(-(2**62), 2**62, 300).tolist()
    pairs = [*zip(ids[:99], ids[1:100]), *((ids[100], x) for x in ids[101:150]), *((ids[150 + i], ids[150 + j]) for i, j in rng.integers(0, 150, (120, 2)))]
    root = {x: x for p in pairs for x in p if p[0] != p[1]}

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    for a, b in pairs:
        if a != b:
            x, y = find(a), find(b)
            root[max(x, y)] = min(x, y)
    got = components.components(spark.createDataFrame(pairs, "a long, b long")).collect()
    assert sorted(map(tuple, got)) == sorted((x, find(x)) for x in root)
    assert components.components(spark.createDataFrame([], "a long, b long")).count() == 0


def test_forest_equals_brute_force():
    rng = np.random.default_rng(5)
    base = [np.unique(rng.integers(0, 4000, 60)) for _ in range(10)]
    sets = [np.unique(np.concatenate([b[rng.random(len(b)) > 0.06], rng.integers(0, 4000, 2)])).astype(np.uint64) for b in base for _ in range(6)]
    root = list(range(len(sets)))
    find = lambda x: x if root[x] == x else find(root[x])
    for a in range(len(sets)):
        for b in range(a):
            i = len(np.intersect1d(sets[a], sets[b]))
            if i and 100 * i >= 80 * (len(sets[a]) + len(sets[b]) - i):
                root[max(find(a), find(b))] = min(find(a), find(b))
    want = [find(x) for x in range(len(sets))]
    root[:] = range(len(sets))
    for a, b in jaccard_join.forest(sets, 80):
        root[max(find(a), find(b))] = min(find(a), find(b))
    assert [find(x) for x in range(len(sets))] == want


def test_packing(spark):
    import public_tokenizers
    from tokenizers import Tokenizer

    tok = Tokenizer.from_file(public_tokenizers.path("byte_bpe_50k.json"))
    rows = corpus(2) + [(900, "日本 語 <|endoftext|>  x\n \n y"), (901, "z" * 9000), (None, "no id"), (902, "say <|endoftext|> now<|endoftext|>"), (903, "<|endoftext|")]
    assert 50256 in tok.encode(rows[-2][1], add_special_tokens=False).ids
    got = packing.pack(frame(spark, rows), with_ids=True).collect()
    want = Counter((d, np.asarray(tok.encode(t or "", add_special_tokens=False).ids + [1], "<u4").tobytes()) for d, t in rows)
    by_doc, by_seq = {}, {}
    for r in got:
        assert zlib.crc32(bytes(r.ids)) == r.ids_crc32 and len(r.ids) == 4 * r.length
        by_doc.setdefault(r.doc_id, []).append((r.start, bytes(r.ids)))
        by_seq.setdefault(r.sequence_id, []).append((r.offset, r.length))
    assert sum(r.length for r in got) == sum(len(ids) // 4 * n for (_, ids), n in want.items())
    for (d, ids), n in want.items():
        if n == 1 and d != 5:
            assert b"".join(x for _, x in sorted(by_doc[d])) == ids
    padding = 0
    for pieces in by_seq.values():
        at = 0
        for offset, n in sorted(pieces):
            assert offset == at
            at += n
        assert at <= 2048 and len(pieces) <= packing.SEGMENTS
        padding += 0 if at & (at - 1) == 0 else 2048 - at
    assert padding <= 0.02 * sum(r.length for r in got)
    assert packing.pack(frame(spark, [])).count() == 0


def test_both_engines_give_the_ids_of_the_tokenizer():
    import public_tokenizers
    from tokenizers import Tokenizer

    path = public_tokenizers.path("byte_bpe_50k.json")
    tok, enc, rng = Tokenizer.from_file(path), packing.Encoder(path), random.Random(5)
    chars = [chr(i) for i in range(256)]
    odd = ["<|endoftext|>", "<|endoftext", "  ", "\n\n", "'ll", "'S", "²³¹¼", "\xa0\x85 ", "12345", "é", "日", "\u2028", "word", " word"]
    texts = ["".join(chars), "", "<|endoftext|>", " <|endoftext|>\n", *("".join(rng.choice(odd + chars) for _ in range(rng.randint(1, 60))) for _ in range(3000))]
    for t in texts:
        assert np.frombuffer(enc.ids(t), "<u4").tolist() == tok.encode(t, add_special_tokens=False).ids, t


def test_vector_bins_keep_all_limits_and_fill_well():
    rng = np.random.default_rng(1)
    items = np.stack([rng.integers(1, 900, 400), np.ones(400, int), rng.integers(0, 300, 400)], 1)
    limits = np.array([2048, 8, 600])
    bins = packing.fill(items, limits, False)
    assert sorted(i for b in bins for i, *_ in b) == list(range(400))
    assert all((items[[i for i, *_ in b]].sum(0) <= limits).all() for b in bins)
    lower = np.ceil(items.sum(0) / limits).max()
    assert len(bins) <= 1.25 * lower
    with pytest.raises(ValueError):
        packing.fill(np.array([[4000, 1, 1]]), limits, False)


def test_pack_examples(spark):
    df = spark.createDataFrame([(i, 100 + i, 10) for i in range(50)] + [(99, 0, 0)], "id long, n_tokens long, n_loss long")
    got = packing.pack_examples(df, (1000, 4, 1000)).collect()
    assert {r.id for r in got} == {*range(50), 99} and max(Counter(r.sequence_id for r in got).values()) <= 4


def test_quality(spark):
    rng = random.Random(4)
    good = lambda: " ".join(rng.choice(["the", "of", "plain", "words", "go", "here", "today."]) for _ in range(rng.randint(20, 200)))
    bad = lambda: " ".join(rng.choice(["!!", "###", "BUY", "BUY!!", "$$$"]) for _ in range(rng.randint(20, 200)))
    rows = [(i, bad() if i % 4 == 0 else good()) for i in range(200)]
    labels = spark.createDataFrame([(i, int(i % 4 != 0), 0) for i in range(100)] + [(None, 1, 0), (3, None, 0)], "doc_id long, quality int, toxic int")
    model = quality.train(frame(spark, rows), labels)
    got = {r.doc_id: r.score for r in quality.score(frame(spark, rows + [(500, None), (501, "")]), model).collect()}
    assert all((got[i] >= 0.3) == (i % 4 != 0) for i in range(100, 200)) and len(got) == 202 and 0 <= got[500] == got[501] <= 1
    none = quality.train(frame(spark, rows), labels.limit(0))
    assert all(0 <= r.score <= 1 for r in quality.score(frame(spark, rows[:3]), none).collect())
    scored = quality.score(frame(spark, rows), model)
    all_ = sorted((r.score for r in scored.collect()), reverse=True)
    for share in (0.005, 0.5, 0.9, 1.0):
        assert quality.keep_best(scored, share).count() == sum(x >= all_[math.ceil(share * 200) - 1] for x in all_)
    twice = frame(spark, rows + rows[:50] + [(7, "x" * 200_000)])  # repeated ids: one row of each is learned, the same each time
    assert (quality.train(twice, labels).weights == quality.train(twice.orderBy(F.rand(3)), labels).weights).all()
    ties = spark.createDataFrame([(i, 0.25) for i in range(9)] + [(9, 0.5), (10, None)], "doc_id long, score double")
    assert [quality.keep_best(ties, s).count() for s in (0.1, 0.2, 1.0)] == [1, 10, 10]
    assert quality.score(frame(spark, []), model).count() == 0


def test_language_id(spark):
    rng = random.Random(6)
    syl = {"en": ["the", "ing", "tion", "and", "wh"], "fr": ["eau", "é", "que", "oi", "aux"], "de": ["sch", "ung", "ein", "ß", "ich"]}
    text = lambda k: " ".join("".join(rng.choice(syl[k]) for _ in range(rng.randint(1, 4))) for _ in range(rng.randint(3, 60)))
    rows = [(i, text(k), k) for i, k in enumerate(rng.choice(list(syl)) for _ in range(300))]
    df = spark.createDataFrame(rows + [(400, None, "en"), (401, "12 !!", "en"), (402, "", None)], "doc_id long, text string, lang string")
    model = langid.train(df.where("doc_id < 200"))
    got = {r.doc_id: r for r in langid.identify(df, model).collect()}
    assert len(got) == 303 and all(got[i].lang_pred == "und" and got[i].rejected and got[i].score == 0 for i in (400, 401, 402))
    assert np.mean([got[i].lang_pred == k for i, _, k in rows[200:]]) > 0.97
    assert sum(got[i].rejected for i, *_ in rows) <= 3
    kept = langid.drop_rejected(df, model)
    assert kept.columns == df.columns and kept.count() >= 297
    assert langid.identify(df.limit(0), model).count() == 0
    assert {r.lang_pred for r in langid.identify(df, langid.train(df.limit(0))).collect()} == {"und"}
    assert model.predict(("é" * (langid.PIECE + 5)).encode())[0] == "fr"
    odd = spark.createDataFrame([(i, t, k, 1, b"x") for i, t, k in rows[:60] + rows[:30]] + [(5, "other words here", "en", 1, b"")], "doc_id long, text string, lang string, bag int, body binary")
    a, b = langid.train(odd), langid.train(odd.orderBy(F.rand(1)))
    assert (a.table == b.table).all() and langid.identify(odd, a).count() == 91 and langid.drop_rejected(odd, a).columns == odd.columns
    assert langid.train(df.where("doc_id < 200"), most_bytes=1).langs  # at least one document, whatever it takes


def test_chat_format_reads_back(spark):
    rng = random.Random(8)
    odd = ["<|im_end|>\n", "<|", "\\", "\\\\<|", "<\\|", "\n", "<", "|", "ok", "é", "", "<|im_start|>assistant\n"]
    rows = [(c, t, rng.choice(["user", "assistant", "sys\ntem", "a\\n", None]), rng.choice([None, "".join(rng.choice(odd) for _ in range(6))])) for c in range(40) for t in range(rng.randint(1, 5))]
    df = spark.createDataFrame(rows + [(None, 0, "user", "x")], "conv_id long, turn long, role string, text string")
    out = chat.format_chat(chat.as_parts(df))
    got = out.select("conv_id", chat.read_turns(F.col("formatted")).alias("t"), chat.loss_text(F.col("formatted"), F.col("loss_spans")).alias("loss")).collect()
    assert len(got) == 41
    for r in got:
        mine = sorted([(t, ro or "", x or "") for c, t, ro, x in [*rows, (None, 0, "user", "x")] if c == r.conv_id])
        assert [(x.role, x.text) for x in r.t] == [(b, c) for _, b, c in mine]
        assert r.loss == "".join(c for _, b, c in mine if b == "assistant")
    assert chat.format_chat(chat.as_parts(df.limit(0))).count() == 0


def test_typed_parts(spark):
    rows = [(1, 0, "user", [("text", "see ", None, None), ("image", None, "a.png", 2), ("audio", None, "b.wav", 10), ("video", None, "c", 1)]), (1, 1, "assistant", [("document", None, "d.pdf", None), ("text", "<|im_end|>", None, None)]), (2, 0, "user", None)]
    df = spark.createDataFrame(rows, f"conv_id long, turn long, role string, parts array<{chat.PART}>")
    got = {r.conv_id: r for r in chat.format_chat(df).collect()}
    assert got[1].formatted == "<|im_start|>user\nsee <|image|><|audio|><|attachment|><|im_end|>\n<|im_start|>assistant\n<|document|><\\|im_end|><|im_end|>\n"
    assert [(a.turn, a.kind, a.ref, a.tokens) for a in got[1].attachments] == [(0, "image", "a.png", 512), (0, "audio", "b.wav", 250), (0, "video", "c", 0), (1, "document", "d.pdf", 500)]
    assert got[1].placeholder_tokens == 1262 and got[2].formatted == "<|im_start|>user\n<|im_end|>\n"


@pytest.mark.parametrize("big", [1.0, 1e4, 1e6])
@pytest.mark.parametrize("small", [False, True])
def test_top_k(spark, big, small, monkeypatch):
    if small:  # many leaves, groups, blocks and nodes; a leaf larger than a group
        for name, value in (("BLOCK", 8), ("NODE_ROWS", 3), ("GROUP", 2), ("PIECE", 2), ("LEAF_ROWS", 10)):
            monkeypatch.setattr(topk, name, value)
    rng = np.random.default_rng(9)
    v = [list(map(float, x)) for x in rng.normal(0, big, (150, 6))]
    v[7] = v[20] = v[40] = v[3]
    rows = [(i, x) for i, x in enumerate(v)] + [(1000, None), (1020, [1.0, None]), (1040, [float("nan")] * 6), (1060, [float("inf")] * 6), (None, v[0]), (1080, [1.0]), (60, v[60])]
    df = spark.createDataFrame([(i, x, 1) for i, x in rows], "vec_id long, embedding array<double>, node int")
    good = [(i, [math.floor(64 * y) for y in x] + [0] * (6 - len(x))) for i, x in rows if i is not None and x is not None and all(y is not None and math.isfinite(y) for y in x)]
    want = set()
    for q, x in {(i, tuple(y)) for i, y in good if i % 20 == 0}:
        best = sorted((-sum(a * b for a, b in zip(x, y, strict=True)), i) for i, y in good if i != q)[:20]
        want |= {(q, k + 1, i, -s) for k, (s, i) in enumerate(best)}
    got = {(r.query_id, r["rank"], r.vec_id, r.score) for r in topk.top_k(df, lambda i: i % 20 == 0).collect()}
    assert got == want
    assert topk.top_k(df.limit(0), lambda i: i % 20 == 0).count() == 0
    few = topk.top_k(df.where("vec_id in (20, 21, 22)"), lambda i: i % 20 == 0).collect()
    assert len(few) == 2
    with pytest.raises(ValueError):
        topk.top_k(spark.createDataFrame([(1, [1e12])], "vec_id long, embedding array<double>"), lambda i: i == 1)


def test_cover_tree_prunes_far_clusters_only():
    rng = np.random.default_rng(2)
    points = np.concatenate([rng.normal(0, 1, (200, 4)) + 100 * np.eye(4)[i] for i in range(4)])
    tree = topk.CoverTree(points, 8)
    near = ((points[:, None] - tree.leaves[None]) ** 2).sum(-1).argmin(1)
    m = len(tree.leaves)
    r = np.array([max([np.linalg.norm(p - tree.leaves[k]) for p in points[near == k]], default=0) for k in range(m)])
    s = points @ points.T
    np.fill_diagonal(s, -np.inf)
    kth = np.sort(s, axis=1)[:, -5]
    worst = np.array([kth[near == k].min() if (near == k).any() else -np.inf for k in range(m)])
    here = np.array([(near == k).any() for k in range(m)])
    live = tree.pairs(r, r, worst, here, here)
    for q in range(len(points)):
        for x in np.argsort(-s[q])[:5]:
            assert live[near[q], near[x]]
    assert live.sum() < here.sum() ** 2
    assert sorted(tree.order()) == list(range(m))


def test_nodes_of_a_block_leave_most_products_out_where_vectors_cluster():
    rng = np.random.default_rng(4)
    kinds = rng.normal(0, 1, (40, 64))
    m = np.floor(64 * (kinds[rng.integers(0, 40, 3000)] + rng.normal(0, 0.05, (3000, 64))))
    order, sizes = topk.nodes_of(m, topk.NODE_ROWS)
    assert sorted(order.tolist()) == list(range(3000)) and sizes.sum() == 3000 and len(sizes) == -(-3000 // topk.NODE_ROWS)
    most = float(np.abs(m).max()) ** 2 * 64
    best = topk.Best(np.arange(0, 3000, 20), m[::20], 20, most)
    for lo in range(0, 3000, 1000):
        part = np.arange(lo, lo + 1000)
        own, n = topk.nodes_of(m[part], topk.NODE_ROWS)
        best.meet(part[own], m[part[own]], n)
    s = m[::20] @ m.T
    s[np.arange(150), np.arange(0, 3000, 20)] = -np.inf
    for i in range(150):
        want = np.lexsort((np.arange(3000), -s[i]))[:20]
        assert best.ids[i].tolist() == want.tolist() and best.score[i].tolist() == s[i][want].tolist()
    assert best.products < 0.55 * s.size


def test_lm_score(spark):
    rng = random.Random(12)
    vocab = {k: [k + "".join(rng.choice("aeiort") for _ in range(rng.randint(1, 5))) for _ in range(60)] for k in "xyz"}
    rows = []
    for i in range(300):
        k = rng.choice("xyz")
        rows.append((i, " ".join(rng.choice(vocab[k][:10] if rng.random() < 0.7 else vocab[k]) for _ in range(rng.randint(5, 60))).capitalize()))
    rows += [(900, None), (901, ""), (902, "neverseen Word " + "q" * 3000), (902, "x")]
    train = lambda d: d < 200
    got = lm_score.score_documents(frame(spark, rows), train).collect()
    assert len(got) == len(rows)
    c = Counter()
    for d, t in rows:
        if d < 200:
            c.update([*words(t, True), None])
    n, v = sum(c.values()), len(c)
    texts = {}
    for d, t in rows:
        texts.setdefault(d, []).append([*words(t, True), None])
    for r in got:
        options = [(len(t), sum(c[w] > 0 for w in t), sum(math.log10((c[w] + 1) / (n + v + 1)) for w in t)) for t in texts[r.doc_id]]
        assert any((r.n_tokens, r.n_known) == o[:2] and abs(r.base_score - o[2]) < 1e-6 for o in options) and r.train_tokens == n
        assert r.score < 0 and math.isfinite(r.score) and r.bits_per_byte > 0
    held = [r for r in got if 200 <= r.doc_id < 300]
    assert sum(r.score for r in held) > sum(r.base_score for r in held)
    assert lm_score.score_documents(frame(spark, []), train).count() == 0
    assert lm_score.score_documents(frame(spark, rows[:5]), lambda d: d > 10**6).count() == 5


SLOTS = 18


def test_bit_predictions_sum_to_one():
    z = np.zeros(2, int)
    zeros, ones = np.zeros(1 << SLOTS), np.zeros(1 << SLOTS)
    body, length = np.frombuffer(b"abcab", np.uint8), np.array([3, 2])
    lm_score.count_bits(body, length, z, np.array([5, 3]), zeros, ones)
    m = lm_score.Mixer(zeros, ones, 0.1)
    m.learn(body, length, z, np.array([5.0, 3.0]))
    s, _, c = lm_score.symbols(body, length, z)
    for k, likeliest in enumerate(b"abc abc"):  # after every prefix the 256 next bytes share one; "abc" is more frequent than "ab"
        p = 10 ** m.symbol_log10(np.arange(256, dtype=np.uint8), np.repeat(c[:, k : k + 1], 256, 1))
        assert abs(p.sum() - 1) < 1e-5 and p.argmax() == likeliest
    assert abs(m.log10(body, length, z).sum() - m.symbol_log10(s, c).sum()) < 1e-9


def slow_word(text, z, table, bits, weights, map_):
    """log10 bitwise probability of one word, step by step in plain Python; with weights None its (slot, bit) pairs for each context."""
    M, s = 0xFFFFFFFF, [*text.encode(), 32]
    total, pairs = 0.0, []
    for at, symbol in enumerate(s):
        past = [s[at - k - 1] if at > k else 0 for k in range(4)]
        run = sum((x + 1) * pow(0x9E3779B97F4A7C15, i, 1 << 64) for i, x in enumerate(s[:at])) % (1 << 64)
        x = run ^ (run >> 30)
        x = x * 0xBF58476D1CE4E5B9 % (1 << 64)
        x ^= x >> 27
        x = x * 0x94D049BB133111EB % (1 << 64)
        x ^= x >> 31
        c = [min(at, 3)]
        for p in past:
            c.append(((c[-1] if len(c) > 1 else 0) << 8 | p) & M)
        c.append(x >> 32)
        contexts = []
        for k, v in enumerate(c):
            h = (v + (0x9E3779B1 * (k + 1) & M) + z * 0x3C6EF372) * 0x85EBCA6B & M
            contexts.append((h ^ h >> 13) * 0xC2B2AE35 & M)
        partial = 1
        for b in range(7, -1, -1):
            bit, ins, seen = symbol >> b & 1, [], 0
            for v in contexts:
                h = (v ^ (partial * 0x27D4EB2F & M)) * 0x165667B1 & M
                i = ((h ^ h >> 15) * 0x9E3779B1 & M) >> 32 - bits
                pairs.append((i, bit))
                n0, n1 = table[i]
                seen = n0 + n1
                ins.append(max(-12, min(12, math.log((n1 + 0.05) / (n0 + 0.05)) * min(1, seen / 2))))
            if weights is not None:
                gate = min(15, int(math.log2(1 + seen)))
                y = sum(w * x for w, x in zip(weights[gate], [*ins, 1.0], strict=True))
                spot = (max(-7.999, min(7.999, y)) + 8) * 2
                lo = int(spot)
                refined = map_[gate][lo] * (1 - spot + lo) + map_[gate][lo + 1] * (spot - lo)
                p = min(1 - 1e-6, max(1e-6, 0.5 / (1 + math.exp(-max(-30, min(30, y)))) + 0.5 * refined))
                total += math.log10(p if bit else 1 - p)
            partial = partial << 1 | bit
    return pairs if weights is None else total


def test_lm_score_equals_brute_force(spark, monkeypatch):
    rng = random.Random(3)
    rows = [(i, " ".join(f"{rng.choice('ab')}{rng.choice(['la', 'Lo', 'é', 'x' * 9])}{rng.randrange(4)}" for _ in range(rng.randint(0, 12)))) for i in range(60)] + [(61, None)]
    train = lambda d: d < 40
    held = {}
    fit, merge, score = lm_score.fit_classes, lm_score.merged, lm_score._score_words
    monkeypatch.setattr(lm_score, "fit_classes", lambda *a: held.setdefault("classes", fit(*a)))
    monkeypatch.setattr(lm_score, "merged", lambda model, learned: (merge(model, learned), held.setdefault("model", model))[0])
    monkeypatch.setattr(lm_score, "_score_words", lambda share, sizes: held.update(share=share) or score(share, sizes))
    got = {r.doc_id: r.score for r in lm_score.score_documents(frame(spark, rows), train).collect()}
    classes, model, share = held["classes"], held["model"], held["share"]
    of = {}
    for d, t in rows:
        bags = [int(h) >> 64 - lm_score.CLASS_BITS for h in hashed_words((t or "").encode().translate(LOWER))]
        of[d] = max(range(lm_score.CLASSES), key=lambda z: (classes.prior[z] + sum(float(classes.theta[z, b]) for b in bags), -z))
    count = Counter((w, of[d]) for d, t in rows if d < 40 for w in words(t, True))
    table = [[0.0, 0.0] for _ in range(1 << model.bits)]
    for (w, z), n in count.items():
        for i, bit in slow_word(w, z, table, model.bits, None, None):
            table[i][bit] += n
    sizes = Counter()
    for (_, z), n in count.items():
        sizes[z] += n
    total = sum(sizes.values())
    p_end = (40 + 1) / (total + 40 + 2)
    known = {}
    for d, t in rows:
        ws, want = words(t, True), float(classes.log10_prior[of[d]]) + math.log10(p_end)
        for w in ws:
            key = (w, of[d])
            if key not in known:
                bits = slow_word(w, of[d], table, model.bits, model.weights.tolist(), model.map.tolist())
                known[key] = math.log10(share * count[key] / max(1, sizes[of[d]]) + (1 - share) * 10**bits)
            want += known[key] + math.log10(1 - p_end)
        assert abs(got[d] - want) < 1e-3 * (1 + len(ws)), d


def slow_text(text, z, table, bits, weights, map_, before="    ", longest=5, first=0, last=10**9):
    """slow_word for the symbols first to last of a word that follows other text: the contexts of one to four bytes reach before it."""
    M, s, back = 0xFFFFFFFF, [*text.encode(), 32], [*before.encode()]
    total, pairs, mixed = 0.0, [], lambda x, k: (x ^ x >> k) & (1 << 64) - 1
    for at, symbol in list(enumerate(s))[first:last]:
        past = [(back + s)[len(back) + at - k - 1] for k in range(4)]
        x = sum((v + 1) * pow(0x9E3779B97F4A7C15, i, 1 << 64) for i, v in enumerate(s[:at])) % (1 << 64)
        x = mixed(mixed(mixed(x, 30) * 0xBF58476D1CE4E5B9 % (1 << 64), 27) * 0x94D049BB133111EB % (1 << 64), 31)
        c = [min(at, 3), *(sum(past[i] << 8 * (k - i) for i in range(k + 1)) for k in range(4)), x >> 32]
        hashed = [(v + (0x9E3779B1 * (k + 1) & M) + z * 0x3C6EF372) * 0x85EBCA6B & M for k, v in enumerate(c)]
        hashed = [(h ^ h >> 13) * 0xC2B2AE35 & M for h in hashed]
        partial = 1
        for b in range(7, -1, -1):
            bit, ins = symbol >> b & 1, []
            for k, v in enumerate(hashed):
                h = (v ^ (partial * 0x27D4EB2F & M)) * 0x165667B1 & M
                i = ((h ^ h >> 15) * 0x9E3779B1 & M) >> 32 - bits
                pairs.append((i, bit))
                n0, n1 = table[i]
                seen = n0 + n1 if k == longest else seen if k else 0
                ins.append(max(-12, min(12, math.log((n1 + 0.05) / (n0 + 0.05)) * min(1, (n0 + n1) / 2))))
            if weights is not None:
                gate = min(15, int(math.log2(1 + seen)))
                y = sum(w * x for w, x in zip(weights[gate], [*ins, 1.0], strict=True))
                spot = (max(-7.999, min(7.999, y)) + 8) * 2
                lo = int(spot)
                refined = map_[gate][lo] * (1 - spot + lo) + map_[gate][lo + 1] * (spot - lo)
                p = min(1 - 1e-6, max(1e-6, 0.5 / (1 + math.exp(-max(-30, min(30, y)))) + 0.5 * refined))
                total += math.log10(p if bit else 1 - p)
            partial = partial << 1 | bit
    return pairs if weights is None else total


def test_lm_score_across_words_equals_brute_force(spark, monkeypatch):
    rng = random.Random(4)
    rows = [(i, "  ".join(f"{rng.choice(['a', 'b', 'Ab', 'abc'])}{rng.choice(['', 'la', 'é', 'x' * 9])}" for _ in range(rng.randint(0, 12)))) for i in range(60)]
    rows += [(61, None), (62, "\tabc a\nb"), (63, "a abc b"), (64, "neverseen " + "q" * 3000)]
    held = {}
    fit, merge = lm_score.fit_classes, lm_score.merged
    monkeypatch.setattr(lm_score, "fit_classes", lambda *a: held.setdefault("classes", fit(*a)))
    monkeypatch.setattr(lm_score, "merged", lambda model, learned: (merge(model, learned), held.setdefault(model.longest, model))[0])
    got = {r.doc_id: r.score for r in lm_score.score_documents(frame(spark, rows), lambda d: d < 40, across=True).collect()}
    classes, late, early = held["classes"], held[5], held[4]
    said = {d: words(t, True) for d, t in rows}
    of = {d: classes.of(hashed_words((t or "").encode().translate(LOWER))) for d, t in rows}
    table, count, sizes = [[0.0, 0.0] for _ in range(1 << late.bits)], Counter(), Counter()
    for d in range(40):
        for k, w in enumerate(said[d]):
            before = " ".join([" " * 3, *said[d][:k], ""])
            for z, span in ((8, (before, 4, 0, 3)), (of[d], ("\0", 5, 3))):
                for i, bit in slow_text(w, z, table, late.bits, None, None, *span):
                    table[i][bit] += 1
            count[w, of[d]] += 1
            sizes[of[d]] += 1
    total = sum(sizes.values())
    p_end = (40 + 1) / (total + 40 + 2)
    weights, map_, weights_e, map_e = late.weights.tolist(), late.map.tolist(), early.weights.tolist(), early.map.tolist()
    for d in said:
        parts = [0.0 for _ in lm_score.PARTS]
        for k, w in enumerate(said[d]):
            before = " ".join([" " * 3, *said[d][:k], ""])
            bits = slow_text(w, 8, table, late.bits, weights_e, map_e, before, 4, 0, 3) + slow_text(w, of[d], table, late.bits, weights, map_, "\0", 5, 3)
            often = count[w, of[d]] / max(1, sizes[of[d]])
            for i, x in enumerate(lm_score.PARTS):
                parts[i] += math.log10(x * often + (1 - x) * 10**bits) if often else math.log10(1 - x) + bits
        most = max(parts)
        want = most + math.log10(sum(10 ** (p - most) for p in parts) / len(parts)) + float(classes.log10_prior[of[d]]) + math.log10(p_end) + len(said[d]) * math.log10(1 - p_end)
        assert abs(got[d] - want) < 1e-3 * (1 + len(said[d])), d
    assert abs(got[62] - got[63]) > 0.01  # the same words in another order


def test_word_order_enters_the_query(spark, tmp_path):
    rows = [(d, "wet rope sank; old ship swam; " * 3) for d in range(30) if zlib.crc32(str(d).encode()) % 7 != 2] + [(100, "wet rope sank; old ship swam;"), (101, "swam; sank; ship old rope wet")]
    spark.createDataFrame(rows, "doc_id long, text string").write.parquet(f"{tmp_path}/documents.parquet")
    got = {r.doc_id: r.score for r in queries.op10_lm_score(spark, str(tmp_path)).collect()}
    assert got[100] > got[101] + 0.5


def test_heads_of_words():
    for raw in (b"", b"  ", b"a", b"ab cde  fghij\nk lm", b"\tabcd e \xc3\xa9\0 ", b"abc"):
        text, want, parts = b"    ", [], []
        for k, w in enumerate(raw.split()):
            want.append(text[-4:] + (w + b"   ")[:3] + b" ")
            for i in range(min(3, len(w) + 1)):
                s = text + w + b" "
                parts.append((s[len(text) + i - 4 : len(text) + i + 1], k))
            text += w + b" "
        keys = lm_score.head_keys([raw, b" ", raw])
        n = len(want)
        got = [int(x).to_bytes(8, "big") for x in keys.tolist()]
        assert [x[:7] for x in got] == [x[:7] for x in want] * 2
        x, of = lm_score.head_symbols(keys[:n])
        assert sorted(zip((int(v).to_bytes(5, "big") for v in x.tolist()), of.tolist(), strict=True)) == sorted(parts)
        assert (lm_score._unpacked(lm_score._packed(x)) == x).all()


def test_texts_of_a_model_are_hashed_together(monkeypatch):
    rng = random.Random(8)
    bodies = [None, b"", b" \t ", b"x" * 300_000 + b" B", b" " * 300_000, *(" ".join(rng.choice("Ab é cd\n e \v f".split(" ")) for _ in range(rng.randint(0, 40))).encode() for _ in range(195))]
    lower = [(b or b"").translate(LOWER) for b in bodies]
    hashes = [hashed_words(b) for b in lower]
    classes = lm_score.Classes([])
    classes.theta = np.random.default_rng(8).normal(size=classes.theta.shape).astype(np.float32)
    of = [classes.of(h) for h in hashes]
    key = [lm_score.keyed(h, z) for h, z in zip(hashes, of, strict=True)]
    assert len(set(of)) > 2
    calls, hash_ = [], lm_score.word_hashes
    monkeypatch.setattr(lm_score, "word_hashes", lambda *a: calls.append(0) or hash_(*a))
    docs, at, held, got = lm_score._slice_words(pa.table({"slice": [1] * 200, "body": pa.array(bodies, pa.binary())}), 5, classes)
    assert list(got) == of and held == len(set(np.concatenate(key).tolist())) and [d.tolist() for d in docs] == [k.tolist() for k in key]
    train = [i % 3 > 0 for i in range(200)]
    rows = lm_score.batch(pa.schema([("doc_id", pa.int64()), ("body", pa.binary()), ("train", pa.bool_())]), [list(range(200)), bodies, train])
    assert [b for x in lm_score._bags([rows]) for b in x.column("h").to_pylist()] == [lm_score.bag(h).astype("<i2").tobytes() for h in hashes]
    want, said = Counter(), {}
    for k, b, t in zip(key, lower, train, strict=True):
        for x, w in zip(k.tolist(), re.findall(rb"[^\x20\x09-\x0D]+", b), strict=True):
            want[x] += t
            said[x] = w
    n, words_ = Counter(), {}
    for x in lm_score._words([rows], 5, classes):
        for h, c, length, body in zip(*(x.column(i).to_pylist() for i in range(1, 5)), strict=True):
            h, length = np.frombuffer(h, "<u8").tolist(), np.frombuffer(length, "<i4")
            for k, c_, w in zip(h, np.frombuffer(c, "<i8").tolist(), np.split(np.frombuffer(body, np.uint8), np.cumsum(length)[:-1]), strict=True):
                n[k] += c_
                words_[k] = w.tobytes()
    assert n == want and words_ == said
    assert len(calls) <= 4  # not once a text


def test_a_learning_step_equals_sums_over_each_gate():
    rng = np.random.default_rng(6)
    model = lm_score.Mixer(np.zeros(1 << 16), np.zeros(1 << 16), 0.1)
    model.weights = rng.normal(size=model.weights.shape).astype(np.float32)
    weights, map_ = model.weights.astype(float), model.map.astype(float)
    for gates in ([3], [0, 2, 15], list(range(16))):
        gate = np.sort(rng.choice(gates, 300))
        x, bit, w = rng.normal(size=(7, 300)).astype(np.float32), rng.integers(0, 2, 300), rng.random(300) * 9
        saw = model._step(x, gate, bit, w, 0.4)
        z = [float(weights[g] @ x[:, i]) for i, g in enumerate(gate)]
        step, total = np.zeros_like(weights), np.zeros(16)
        for i, g in enumerate(gate):
            step[g] += w[i] * (bit[i] - 1 / (1 + math.exp(-z[i]))) * x[:, i]
            total[g] += w[i]
        weights += 0.1 / np.maximum(total, 32)[:, None] * step
        for side in (0, 1):
            both = np.zeros((*map_.shape, 2))
            for i, g in enumerate(gate):
                y = (min(7.999, max(-7.999, z[i])) + 8) * 2
                both[g, int(y) + side, bit[i]] += w[i] * (y - int(y) if side else 1 - y + int(y))
            map_ = (map_ * 20 + both[..., 1]) / (20 + both.sum(2))
        assert np.allclose(saw, total) and np.allclose(model.weights, weights, atol=1e-4) and np.allclose(model.map, map_, atol=1e-4)


def test_slots_follow_the_lexicon():
    assert [lm_score.slot_bits(n) for n in (0, 10**4, 10**5, 10**9)] == [16, 17, 21, 22]


def test_rare_words_count_in_all_contexts():
    body, length, z = np.frombuffer(b"abcdef", np.uint8), np.array([6]), np.zeros(1, int)
    for weight in (1, 2, 3):
        zeros, ones = np.zeros(1 << SLOTS), np.zeros(1 << SLOTS)
        lm_score.count_bits(body, length, z, np.array([weight]), zeros, ones)
        assert zeros.sum() + ones.sum() == weight * 7 * 8 * lm_score.ORDERS
        s, _, c = lm_score.symbols(body, length, z)
        for k in range(lm_score.ORDERS):
            i = lm_score.slots(c[k], np.ones(len(s), np.uint32), SLOTS)
            assert (zeros[i] + ones[i] >= weight).all()


def test_classes_and_mixer_learn_from_all_rows(spark, monkeypatch):
    monkeypatch.setattr(lm_score, "CLASS_SAMPLE", 2)
    rows = [(i, " ".join(f"{'pqrs'[i % 4]}{j}" for j in range(i, i + 30))) for i in range(200)]
    classes = lm_score.fit_classes(frame(spark, rows), lambda d: d.isNotNull())
    n = np.rint(np.exp(classes.prior) * (len(rows) + lm_score.CLASSES) - 1)
    assert n.sum() == len(rows)  # every training document is in a class
    tables = SimpleNamespace(value=np.zeros((2, 1 << SLOTS)))
    lex = lm_score.batch(lm_score._LEX_PA, [[0], [np.arange(3, dtype="<u8").tobytes()], [np.array([1, 9, 0], "<i8").tobytes()], [np.full(3, 2, "<i4").tobytes()], [b"aabbcc"]])
    (got,) = [b.to_pylist()[0] for b in lm_score._learn(tables, 0.1)([lex])]
    assert abs(np.frombuffer(got["saw"], "<f8").sum() - 10 * 3 * 8) < 1e-6  # each of the ten training tokens, bit by bit


def test_pipeline_stages(spark, tmp_path):
    import corpus_pipeline

    rng = random.Random(20)
    text = lambda: " ".join("".join(rng.choice(["the", "ing", "an", "er"]) for _ in range(rng.randint(1, 4))) for _ in range(80))
    item = text()
    clean = [text() for _ in range(40)]
    rows = [(i, t, "en", "s", len(t)) for i, t in enumerate(clean)]
    rows += [(100, clean[0], "en", "s", 1), (101, clean[1] + " more", "en", "s", 1), (102, "1234 !!", "en", "s", 1), (103, f"{text()} {item} {text()}", "en", "s", 1), (104, None, None, None, None), (3, clean[3], "en", "s", 1)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long")
    docs.write.parquet(f"{tmp_path}/documents.parquet")
    spark.createDataFrame([(1, item)], "item_id long, text string").write.parquet(f"{tmp_path}/benchmark.parquet")
    out = docs
    for name, stage in corpus_pipeline.STAGES[:-1]:
        out = stage(spark, out, str(tmp_path))
        assert out.columns == docs.columns
    left = sorted(r.doc_id for r in out.collect())
    assert left == list(range(40))
    packed = corpus_pipeline.run(spark, str(tmp_path))
    assert {r.doc_id for r in packed.collect()} == set(range(40))
    assert [n for n, _ in corpus_pipeline.STAGES] == ["language_id", "line_dedup", "ngram_jaccard_join", "benchmark_decontamination", "packing"]


def test_pipeline_sends_small_batches(spark):
    keys = ["spark.sql.execution.arrow.maxRecordsPerBatch", "spark.sql.execution.arrow.maxBytesPerBatch"]
    before = [spark.conf.get(k) for k in keys]
    sizes = lambda: [r.n for r in spark.range(0, 5000, 1, 1).mapInArrow(lambda it: (pa.RecordBatch.from_pydict({"n": [b.num_rows]}) for b in it), "n long").collect()]
    try:
        docs = frame(spark, [(i, "the quick brown fox jumps over the lazy dog " * 3) for i in range(20)]).select("doc_id", "text", F.lit("en").alias("lang"))
        stages.language_id(spark, docs, "").count()
        assert max(sizes()) <= 1000 and sum(sizes()) == 5000
        spark.conf.set(keys[0], "10")
        stages.language_id(spark, docs, "")
        assert spark.conf.get(keys[0]) == "10"
    finally:
        for k, v in zip(keys, before, strict=True):
            spark.conf.set(k, v)


def test_native_operators_run_no_python(spark):
    sf = "/root/testdata/sf0.001"
    for q in (queries.op1_line_dedup, queries.op3_decontamination, queries.op7_chat_format):
        plan = q(spark, sf)._jdf.queryExecution().executedPlan().toString()
        assert not re.search("Python|Pandas|Arrow", plan)
