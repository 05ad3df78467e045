"""Each operator against brute force on small tables, with the odd cases of every column."""

import collections
import hashlib
import random
import re

import numpy as np
import pytest

WS = " \t\n\x0b\x0c\r"
WORDS = [a + b for a in "ka lo mi nu te so ra".split() for b in "ba de fi go hu".split()]


def table(spark, texts, ids=None):
    rows = [(i if ids is None else ids[i], t, ["en", "fr", None][i % 3], ["a", "b", None][i % 3], 7, "x") for i, t in enumerate(texts)]
    return spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long, digest string")


def prose(rng, n):
    return " ".join(rng.choice(WORDS) for _ in range(n))


def odd_texts(rng):
    base = prose(rng, 90)
    w = base.split()
    near = " ".join(w[:40] + ["other"] + w[41:])
    line = "A Common Line of the corpus"
    texts = [None, "", " \n ", "one", "one two three", base, base, base.upper(), near, base.replace(" ", "\n"), "\n".join([line, prose(rng, 12)]), "  " + line.lower() + "\t\n" + prose(rng, 9), line + "\n\n" + line, prose(rng, 400), "é ü x \x1c y", "a " * 300, "x" * 3000]
    return texts + [prose(rng, rng.randint(0, 60)) for _ in range(20)] + [near, prose(rng, 2)]


@pytest.fixture(scope="module")
def texts():
    return odd_texts(random.Random(3))


def sha(b):
    return hashlib.sha256(b if isinstance(b, bytes) else b.encode()).hexdigest()


# ---------------------------------------------------------------- line dedup


def brute_lines(texts):
    low = str.maketrans("ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")
    key = lambda x: x.strip(WS).translate(low)
    held = collections.defaultdict(set)
    for i, t in enumerate(texts):
        for x in (t or "").split("\n"):
            held[key(x)].add(i)
    out = {}
    for i, t in enumerate(texts):
        lines = (t or "").split("\n")
        kept = [x for x in lines if not (len(key(x)) >= 20 and len(held[key(x)]) >= 3 and max(held[key(x)]) != i)]
        out[i] = (len(lines), len(lines) - len(kept), sha("\n".join(kept)))
    return out


def test_line_dedup(spark, texts):
    from fullgraph.llm import line_dedup

    got = {r.doc_id: (r.n_lines, r.n_dropped, r.kept_sha256) for r in line_dedup.digest(table(spark, texts)).collect()}
    assert got == brute_lines(texts)
    assert sum(v[1] for v in got.values()) > 0
    assert line_dedup.digest(table(spark, [])).count() == 0


# ---------------------------------------------------------------- quality rules


def test_quality_rules(spark, texts):
    from fullgraph.llm import quality_rules

    got = {r.doc_id: r for r in quality_rules.judge(table(spark, texts)).collect()}
    for i, t in enumerate(texts):
        t = t or ""
        words = re.findall("[^\x20\x09-\x0d]+", t)
        grams = [tuple(words[j : j + 3]) for j in range(len(words) - 2)]
        n = collections.Counter(grams)
        rep = {j + d for j, g in enumerate(grams) if n[g] > 1 for d in range(3)}
        lines = [x for x in t.split("\n") if x.strip(WS)]
        want = (len(words), sum(map(len, words)), sum(c in "#*$%&|<>" for c in t), len(lines) - len(set(lines)), len(rep))
        r = got[i]
        assert (r.n_words, r.word_chars, r.n_symbols, r.n_dup_lines, r.n_repeat_words) == want, i
        assert r.base_failed == (len(words) < 50 or 100 * len(rep) > 50 * len(words))
        assert not (r.base_failed and r.kept)
    assert quality_rules.digest(table(spark, [])).count() == 0


def test_quality_plan_is_native(spark):
    from fullgraph.llm import quality_rules

    plan = quality_rules.digest(table(spark, ["a"]))._jdf.queryExecution().toString()
    assert "Python" not in plan and "Arrow" not in plan and "Exchange" not in plan


# ---------------------------------------------------------------- exact dedup


def brute_exact(texts):
    norm = [re.sub("[\x20\x09-\x0d]", "", t or "") for t in texts]
    groups = collections.defaultdict(list)
    for i, n in enumerate(norm):
        groups[n].append(i)
    out = {}
    for n, ids in groups.items():
        keep = min(ids, key=lambda i: (-len(texts[i] or ""), i))
        for i in ids:
            out[i] = (keep, len(ids), i == keep, sha(n))
    return out


@pytest.mark.parametrize("weak", [False, True])
def test_exact_dedup(spark, texts, weak):
    from pyspark.sql import functions as F

    from fullgraph.llm import exact_dedup

    key = exact_dedup.sha_key if not weak else lambda norm: F.unhex(F.concat(F.lit("0"), F.substring(F.sha2(norm, 256), 1, 1)))
    rows = exact_dedup.exact_groups(spark, table(spark, texts).repartition(3), key, max_files_per_batch=1).collect()
    assert {r.doc_id: (r.keep_id, r.group_size, r.kept, r.text_sha256) for r in rows} == brute_exact(texts)
    assert len(rows) == len(texts)


def test_exact_dedup_odd_tables(spark, tmp_path):
    from fullgraph.llm import exact_dedup

    assert exact_dedup.exact_groups(spark, table(spark, [])).count() == 0
    twice = table(spark, ["a b", "a b", "ab"], ids=[4, 4, None])
    path = str(tmp_path / "t")
    twice.write.parquet(path)
    rows = exact_dedup.exact_groups(spark, spark.read.parquet(path)).collect()
    assert len(rows) == 3 and sum(r.kept for r in rows) == 1 and {r.keep_id for r in rows} == {4}
    assert exact_dedup.deduplicate(spark, spark.read.parquet(path)).columns == twice.columns
    assert exact_dedup.deduplicate(spark, spark.read.parquet(path)).count() == 1


def test_exact_dedup_resumes(spark, tmp_path):
    from fullgraph.llm import exact_dedup

    src, folder = str(tmp_path / "in"), str(tmp_path / "state")
    first = exact_dedup.fingerprints(table(spark, ["a", "b"]))
    first.write.parquet(src)
    session = spark.newSession()
    exact_dedup.run_stream(spark, session.readStream.schema(first.schema).parquet(src), folder)
    exact_dedup.fingerprints(table(spark, [" a"], ids=[9])).write.mode("append").parquet(src)
    state = exact_dedup.run_stream(spark, session.readStream.schema(first.schema).parquet(src), folder)
    assert sorted((r.survivor.doc_id, r.seen) for r in state.collect()) == [(1, 1), (9, 2)]


# ---------------------------------------------------------------- suffix arrays


def brute_spans(texts, n):
    raws = [(t or "").encode() for t in texts]
    seen = collections.Counter(r[i : i + n] for r in raws for i in range(len(r) - n + 1))
    out = {}
    for k, r in enumerate(raws):
        gone = np.zeros(len(r) + 1, dtype=int)
        for i in range(len(r) - n + 1):
            if seen[r[i : i + n]] > 1:
                gone[i : i + n] = 1
        gone = gone[: len(r)]
        spans = int((np.diff(np.concatenate([[0], gone])) == 1).sum())
        out[k] = (len(r), int(gone.sum()), spans, sha(bytes(b for b, g in zip(r, gone) if not g)))
    return out


def test_suffix_array():
    from fullgraph.llm.suffix_array import suffix_array

    rng = random.Random(1)
    for _ in range(25):
        s = bytes(rng.choice(b"ab") for _ in range(rng.randint(1, 80)))
        assert suffix_array(s).tolist() == sorted(range(len(s)), key=lambda i: s[i:])


@pytest.mark.parametrize("max_group", [4096, 3])
def test_suffix_dedup(spark, max_group):
    from fullgraph.llm import suffix_dedup

    rng = random.Random(max_group)
    gen = lambda n: "".join(rng.choice("abcdé fghij\n") for _ in range(n))
    common = [gen(rng.randint(390, 900)) for _ in range(4)]
    texts = [None, "", "a" * 900, gen(300)]
    for _ in range(25):
        parts = [gen(rng.randint(0, 400))]
        for _ in range(rng.randint(0, 2)):
            p = rng.choice(common)
            parts += [p[rng.randint(0, 60) : len(p) - rng.randint(0, 60)], gen(rng.randint(0, 200))]
        texts.append("".join(parts))
    texts += [texts[8], texts[9] + texts[9]]
    rows = suffix_dedup.remove_repeats(spark, table(spark, texts), max_group=max_group).collect()
    got = {r.doc_id: (r.n_bytes, r.n_removed, r.n_spans, sha(bytes(r.kept))) for r in rows}
    assert got == brute_spans(texts, 400)
    if max_group > 3:
        assert suffix_dedup.digest(spark, table(spark, [])).count() == 0


# ---------------------------------------------------------------- chaining


def test_chains_are_best():
    from fullgraph.llm.chaining import chains

    rng = random.Random(5)
    for _ in range(60):
        m = sorted({(rng.randint(0, 60), rng.randint(0, 60)) for _ in range(rng.randint(1, 25))})
        best = {}
        for x, y in m:
            best[x, y] = max([6.0, *(best[a, b] + 6 - 0.1 * (x - a + y - b) for a, b in best if a < x and b < y)])
        chain = chains(m)[0]
        score = 6.0 * len(chain) - 0.1 * (chain[-1][0] - chain[0][0] + chain[-1][1] - chain[0][1])
        assert abs(score - max(best.values())) < 1e-9
        assert all(a[0] < b[0] and a[1] < b[1] for a, b in zip(chain, chain[1:]))
        assert sorted(x for c in chains(m) for x in c) == m


def test_common_subsequence():
    from fullgraph.llm.chaining import common_subsequence

    rng = random.Random(6)
    for _ in range(50):
        a, b = ([rng.randint(0, 3) for _ in range(rng.randint(0, 12))] for _ in range(2))
        t = [[0] * (len(b) + 1) for _ in range(len(a) + 1)]
        for i, x in enumerate(a):
            for j, y in enumerate(b):
                t[i + 1][j + 1] = t[i][j] + 1 if x == y else max(t[i][j + 1], t[i + 1][j])
        assert common_subsequence(a, b) == t[-1][-1]


def test_fuzzy_passages(spark):
    from fullgraph.llm import chaining

    rng = random.Random(8)
    vocabulary = [f"w{i}" for i in range(5000)]
    text = lambda n: [rng.choice(vocabulary) for _ in range(n)]
    passage = text(70)
    edited = passage[:30] + ["new"] + passage[31:50] + passage[51:]
    texts = [text(50) + passage + text(50), text(80), text(20) + edited + text(10), passage, text(5) + passage[:25] + text(60), None, "", " ".join(["loop"] * 400), " ".join(["loop"] * 300)]
    texts = [" ".join(t) if isinstance(t, list) else t for t in texts]
    rows = chaining.passages(spark, table(spark, texts)).collect()
    pairs = {(r.doc_id, r.ref_doc_id) for r in rows}
    assert {(2, 0), (3, 0)} <= pairs and all(1 not in p and 4 not in p for p in pairs)
    r = next(r for r in rows if r.doc_id == 3)
    assert (r.start_word, r.n_words, r.ref_start_word, r.matched) == (0, 70, 50, 70)
    r = next(r for r in rows if r.doc_id == 2)
    assert (r.start_word, r.ref_start_word) == (20, 50) and r.matched >= 68
    assert chaining.passages(spark, table(spark, [])).count() == 0


def test_two_passages_of_one_pair(spark):
    from fullgraph.llm import chaining

    rng = random.Random(21)
    vocabulary = [f"w{i}" for i in range(50000)]
    text = lambda n: [rng.choice(vocabulary) for _ in range(n)]
    texts, want = [], set()
    for n, between in [(60, 40), (60, 80), (100, 100), (200, 200)]:
        p, q = text(n), text(n)
        d = len(texts)
        texts += [text(20) + p + text(between) + q + text(20), text(7) + p + text(between) + q + text(9)]
        want |= {(d + 1, d, 7, n, 20, n, n), (d + 1, d, 7 + n + between, n, 20 + n + between, n, n)}
    p = text(400)  # the middle quarter is written anew
    texts += [p, p[:150] + text(100) + p[250:]]
    want |= {(9, 8, 0, 150, 0, 150, 150), (9, 8, 250, 150, 250, 150, 150)}
    assert {tuple(r) for r in chaining.passages(spark, table(spark, [" ".join(t) for t in texts])).collect()} == want


def test_passages_with_evenly_replaced_words(spark):
    from fullgraph.llm import chaining

    rng = random.Random(22)
    vocabulary = [f"w{i}" for i in range(50000)]
    text = lambda n: [rng.choice(vocabulary) for _ in range(n)]
    texts, want = [], set()
    for every in (5, 6, 7, 8, 10):
        for n in (60, 100):
            p = text(n)
            q = [f"new{i}" if i % every == every - 1 else w for i, w in enumerate(p)]
            want.add((len(texts) + 1, len(texts)))
            texts += [text(30) + p + text(30), text(30) + q + text(30)]
    rows = chaining.passages(spark, table(spark, [" ".join(t) for t in texts])).collect()
    assert {(r.doc_id, r.ref_doc_id) for r in rows} == want and len(rows) == len(want)


def test_passages_of_fragments_in_smaller_documents(spark):
    from fullgraph.llm import chaining

    rng = random.Random(23)
    vocabulary = [f"w{i}" for i in range(50000)]
    text = lambda n: [rng.choice(vocabulary) for _ in range(n)]
    texts, want = [], set()
    for cuts in ([(0, 30), (30, 60)], [(0, 25), (15, 40), (35, 60)]):  # two lines; fragments that overlap
        for one in (False, True):
            p = text(60)
            small = [text(20) + p[lo:hi] + text(20) for lo, hi in cuts]
            texts += [sum(small, [])] if one else small
            want.add((len(texts) + 1, len(texts), 11, 60, 33, 60, 60))
            texts += [text(33) + p + text(5), text(11) + p + text(8)]
    p, d = text(60), len(texts)  # all seeds of the passage stand elsewhere in the head before
    texts += [sum((p[i : i + 20] + text(60) for i in range(0, 60, 10)), []) + p, p]
    want.add((d + 1, d, 0, 60, len(texts[d]) - 60, 60, 60))
    assert {tuple(r) for r in chaining.passages(spark, table(spark, [" ".join(t) for t in texts])).collect()} == want


# ---------------------------------------------------------------- packing


def test_packing_round_trip(spark, texts):
    tokenizers = pytest.importorskip("tokenizers")
    from fullgraph.llm import packing

    t = tokenizers.Tokenizer.from_file(packing.default_tokenizer())
    extra = ["don't we'll I'm 12ab½ x²", "naïve ÇA İstanbul ŉ", "a<|endoftext|>b", "日本 語", "é café", "\x85\xa0a\x1cb", prose(random.Random(2), 4000)]
    use = texts + extra
    pieces = collections.defaultdict(list)
    for r in packing.pack(spark, table(spark, use)).collect():
        assert r.offset == 0 and r.length == 1 << r.bucket <= 2048
        pieces[r.doc_id].append(r)
    assert len({r.sequence_id for p in pieces.values() for r in p}) == sum(map(len, pieces.values()))
    for i, x in enumerate(use):
        p = sorted(pieces[i], key=lambda r: r.start)
        ids = np.frombuffer(b"".join(bytes(r.ids) for r in p), dtype="<u4").tolist()
        assert ids == t.encode(x or "", add_special_tokens=False).ids + [1], i
        assert [r.start for r in p] == np.cumsum([0, *[r.length for r in p]])[:-1].tolist()
        assert all(r.doc_tokens == len(ids) for r in p)
    assert packing.pieces(2048 * 2 + 5) == [(0, 2048), (2048, 2048), (4096, 4), (4100, 1)]
    assert packing.digest(spark, table(spark, [])).count() == 0


# ---------------------------------------------------------------- language


def test_language_id(spark):
    from fullgraph.llm import langid

    rng = random.Random(4)
    en, fr = "the and of to with that this".split(), "le la les des pour avec être".split()
    rows = [(i, " ".join(rng.choice(en if i % 2 else fr) for _ in range(30)), "en" if i % 2 else "fr") for i in range(120)]
    rows += [(500, None, "en"), (501, "123 !?", "en"), (502, "the of", None)]
    df = spark.createDataFrame(rows, "doc_id long, text string, lang string")
    got = {r.doc_id: r for r in langid.identify(spark, df).collect()}
    assert all(got[i].lang_pred == rows[i][2] for i in range(120))
    assert got[500].lang_pred == got[501].lang_pred == "und" and got[502].lang_pred == "en"
    assert all(0 <= r.score <= 1 for r in got.values())
    import zlib

    assert all(r.held_out == (zlib.crc32(str(r.doc_id).encode()) % 5 == 0) for r in got.values())
    assert langid.identify(spark, df.limit(0)).count() == 0
    assert {r.lang_pred for r in langid.identify(spark, df.filter("lang is null")).collect()} == {"und"}


def test_language_score_ignores_neighbours():
    from fullgraph.llm.langid import BUCKETS, score_texts

    m = np.log(np.random.default_rng(0).random((BUCKETS, 3))).astype(np.float32)
    alone = [score_texts([t], m)[0] for t in ("ab", "x", "ünï code")]
    assert np.allclose(score_texts(["ab", "x", "ünï code"], m), alone)


# ---------------------------------------------------------------- n-gram Jaccard


def brute_components(texts, k, percent):
    sets = []
    for t in texts:
        w = (t or "").encode().lower().split()
        sets.append({tuple(w[i : i + k]) for i in range(max(1, len(w) - k + 1))} if w else set())
    label = list(range(len(texts)))
    find = lambda i: i if label[i] == i else find(label[i])
    for i, a in enumerate(sets):
        for j in range(i):
            if a and sets[j] and 100 * len(a & sets[j]) >= percent * len(a | sets[j]):
                x, y = find(i), find(j)
                label[max(x, y)] = min(x, y)
    return {i: (len(s), find(i)) for i, s in enumerate(sets)}


@pytest.mark.parametrize("k,percent,tile", [(4, 85, 1024), (2, 60, 3)])
def test_jaccard_join(spark, texts, k, percent, tile, monkeypatch):
    from fullgraph.llm import jaccard_join

    monkeypatch.setattr(jaccard_join, "TILE", tile)
    rng = random.Random(11)
    base = [rng.choice(WORDS) for _ in range(80)]
    more = []
    for _ in range(30):
        w = list(base)
        for _ in range(rng.randint(0, 4)):
            w[rng.randrange(80)] = f"z{rng.randint(0, 99)}"
        more.append(" ".join(w))
    use = texts + more
    got = {r.doc_id: (r.n_shingles, r.component_id) for r in jaccard_join.similar(spark, table(spark, use), k, percent).collect()}
    assert got == brute_components(use, k, percent)


def test_jaccard_odd_tables(spark):
    from fullgraph.llm import jaccard_join

    assert jaccard_join.similar(spark, table(spark, [])).count() == 0
    rows = jaccard_join.similar(spark, table(spark, ["a b c d e", "a b c d e", "a b c d e", None], ids=[3, 3, None, 8])).collect()
    assert sorted((r.doc_id or -1, r.n_shingles, r.component_id) for r in rows if r.doc_id) == [(3, 2, 3), (3, 2, 3), (8, 0, 8)]
    assert [r.component_id for r in rows if r.doc_id is None] == [None]


def test_parity_bitmap_bounds_overlap():
    from fullgraph.llm.jaccard_join import _bits, fold, parity_bitmap

    rng = np.random.default_rng(1)
    for n, m in ((10, 12), (200, 260), (900, 700)):
        shared = rng.integers(0, 2**63, min(n, m) // 2, dtype=np.uint64)
        a, b = (np.unique(np.concatenate([shared, rng.integers(0, 2**63, x - len(shared), dtype=np.uint64)])) for x in (n, m))
        x, y = _bits(parity_bitmap(a)), _bits(parity_bitmap(b))
        w = min(len(x), len(y))
        differ = int(np.bitwise_count(fold(x, w) ^ fold(y, w)).sum())
        assert (len(a) + len(b) - differ) // 2 >= len(np.intersect1d(a, b))


# ---------------------------------------------------------------- toxicity, mixing, pipeline


def test_toxicity_held_out(spark):
    from fullgraph.llm import toxicity

    docs, labels = (spark.read.parquet(f"/root/testdata/sf0.1/{t}.parquet") for t in ("documents", "labels"))
    chain = toxicity.train(spark, docs, labels.filter("doc_id % 2 = 0"))
    scored = toxicity.score(spark, docs, chain).join(labels.filter("doc_id % 2 = 1"), "doc_id").collect()
    clean = [r for r in scored if not r.toxic]
    assert sum(r.is_toxic for r in clean) <= 0.02 * len(clean)
    toxic = [r for r in scored if r.toxic]
    assert sum(r.is_toxic for r in toxic) >= 0.8 * len(toxic)
    assert all(0 <= p <= 1 for r in scored for p in (r.p_weak_a, r.p_weak_b, r.p_toxic))


def test_toxicity_odd_tables(spark, texts):
    from fullgraph.llm import toxicity

    none = spark.createDataFrame([], "doc_id long, quality int, toxic int")
    got = toxicity.classify(spark, table(spark, texts), none).collect()
    assert len(got) == len(texts) and not any(r.is_toxic for r in got)
    assert toxicity.classify(spark, table(spark, []), none).count() == 0
    labels = spark.createDataFrame([(i, 1, None if i == 3 else i % 2) for i in range(len(texts))], "doc_id long, quality int, toxic int")
    assert toxicity.keep_clean(spark, table(spark, texts), labels).columns == table(spark, []).columns


def test_chain_uses_earlier_probabilities():
    from fullgraph.llm.toxicity import fit_chain

    rng = random.Random(0)
    rows = [{"bad": 1.0, f"x{i}": 1.0} if i % 4 == 0 else {f"x{i}": 1.0} for i in range(200)]
    chain = fit_chain(rows, np.array([i % 4 == 0 for i in range(200)], dtype=float))
    assert "bad" in chain.words and [len(w) for w in chain.weights] == [len(chain.words) + 1 + k for k in range(3)]
    x = np.zeros((2, len(chain.words)))
    x[0, chain.words.index("bad")] = 1
    p = chain.probabilities(x)
    assert p[0, -1] > 0.5 > p[1, -1]
    assert rng is not None


def brute_mixing(rows, targets, rounds=50, cap=None):
    """Expected weight per document: raking with dictionaries."""
    cells = collections.Counter()
    for d in rows:
        cells[d["key"]] += d["n"]
    total = sum(cells.values())
    factor = dict.fromkeys(cells, 1.0)
    for _ in range(rounds):
        for m in range(3):
            have = collections.Counter()
            for c, n in cells.items():
                have[c[m]] += n * factor[c]
            for c in cells:
                if have[c[m]] > 0:
                    factor[c] *= targets[m][c[m]] * total / have[c[m]]
        if cap:
            mean = sum(n * factor[c] for c, n in cells.items()) / total
            factor = {c: min(f, cap * mean) for c, f in factor.items()}
    return factor


@pytest.mark.parametrize("given", [False, True])
def test_mixing_against_brute_force_on_both_paths(spark, given):
    from fullgraph.llm import mixing

    docs = spark.read.parquet("/root/testdata/sf0.01/documents.parquet")
    lang = {"en": 0.1, "fr": 0.6, "de": 0.2, "es": 0.1}
    targets = {"lang": lang} if given else None
    a, b = ({(r.doc_id, r.row_hash): r for r in mixing.chances(spark, docs, targets=targets, max_driver_cells=n).collect()} for n in (200_000, 0))
    assert a.keys() == b.keys() and len(a) == docs.count()
    for k, r in a.items():
        assert abs(r.probability - b[k].probability) < 1e-9 and abs(r.weight - b[k].weight) < 1e-9 * max(1, r.weight)
    rows = [{"key": (r.source, r.lang, r.topic), "n": r.n_tokens} for r in a.values()]
    for d, r in zip(rows, a.values()):
        assert d["n"] >= 0 and r.selected == b[r.doc_id, r.row_hash].selected
    want = []
    for m in range(3):
        part = collections.Counter()
        for d in rows:
            part[d["key"][m]] += d["n"]
        part = {k: (lang[k] if given and m == 1 else v**mixing.TEMPER if v else 0.0) for k, v in part.items()}
        want.append({k: v / sum(part.values()) for k, v in part.items()})
    factor = brute_mixing(rows, want, cap=None if given else mixing.MAX_RATIO)
    top = max(f for k, f in factor.items() if any(d["key"] == k and d["n"] for d in rows))
    for d, r in zip(rows, a.values()):
        assert abs(r.weight - factor[d["key"]]) < 1e-6 and abs(r.probability - min(1.0, factor[d["key"]] / top)) < 1e-6
    for r in mixing.achieved(spark, docs, targets=targets).collect():
        assert abs(r.achieved - r.target) < 0.01
        assert not given or r.margin != "lang" or abs(r.target - lang[r.value]) < 1e-12
    got, expected = sum(r.selected for r in a.values()), sum(r.probability for r in a.values())
    assert abs(got - expected) < 4 * np.sqrt(expected)


def test_mixing_reports_what_it_misses(spark):
    from fullgraph.llm import mixing

    docs = spark.createDataFrame([(i, "a b c", "x" if i else "y", "en") for i in range(40)], "doc_id long, text string, source string, lang string")
    with pytest.warns(UserWarning, match="misses"):
        rows = {r.value: r for r in mixing.achieved(spark, docs, targets={"source": {"x": 0.5, "y": 0.5}}, max_ratio=2.0).filter("margin = 'source'").collect()}
    assert rows["y"].achieved < 0.2 and rows["y"].target == 0.5
    rows = {r.value: r for r in mixing.achieved(spark, docs, targets={"source": {"x": 0.5, "y": 0.5}}).filter("margin = 'source'").collect()}
    assert abs(rows["y"].achieved - 0.5) < 1e-9


def test_rake_is_exact():
    from fullgraph.llm.mixing import rake

    tokens = np.array([10.0, 20, 30, 40])
    codes = [np.array([0, 0, 1, 1]), np.array([0, 1, 0, 1])]
    f = rake(tokens, codes, [np.array([0.5, 0.5]), np.array([0.3, 0.7])], 200, 100.0)
    w = tokens * f
    assert np.allclose(np.bincount(codes[0], weights=w) / w.sum(), [0.5, 0.5]) and np.allclose(np.bincount(codes[1], weights=w) / w.sum(), [0.3, 0.7])


def test_mixing_odd_tables(spark, texts):
    from fullgraph.llm import mixing

    assert mixing.calibrated(spark, table(spark, [])).count() == 0
    assert mixing.calibrated(spark, table(spark, texts)).count() == len(texts)
    assert mixing.mix(spark, table(spark, [None, ""])).count() == 2
    assert mixing.mix(spark, table(spark, texts)).columns == table(spark, []).columns


CLASHES = ["_locator", "_kept_locator", "_kept", "_id", "_hash", "_metadata", "_salt", "_hot", "keep_id", "probability", "selected", "row_hash", "topic", "component_id", "n_shingles", "is_toxic", "p_toxic", "weight", "seen", "key", "slot", "bits", "bucket", "norm"]


def test_stages_carry_clashing_columns(spark, texts):
    """The same rows stay as without the extra columns; null and repeated doc_ids, and all values, pass."""
    from pyspark.sql import functions as F

    from fullgraph.llm import exact_dedup, jaccard_join, mixing, toxicity

    plain = table(spark, texts, ids=[None if i == 4 else 7 if i in (5, 6) else i for i in range(len(texts))])
    wide = plain.select("*", *[F.concat(F.lit(c), F.coalesce(F.col("doc_id").cast("string"), F.lit("-"))).alias(c) for c in CLASHES])
    labels = spark.createDataFrame([(i, 1, i % 2) for i in range(len(texts))], "doc_id long, quality int, toxic int")
    stages = {
        "exact": lambda d: exact_dedup.deduplicate(spark, d),
        "near": lambda d: jaccard_join.deduplicate(spark, d),
        "mixing": lambda d: mixing.mix(spark, d),
        "toxicity": lambda d: toxicity.keep_clean(spark, d, labels),
    }
    for name, stage in stages.items():
        source = wide.drop("topic") if name == "mixing" else wide
        got = stage(source)
        assert got.columns == source.columns, name
        rows = got.collect()
        assert all(r[c] == c + ("-" if r.doc_id is None else str(r.doc_id)) for r in rows for c in source.columns if c in CLASHES), name
        key = lambda r: (r.doc_id is None, r.doc_id or 0, r.text or "", r.text is None)
        want = stage(plain).collect()
        if name == "exact":  # of equal rows with one id either may stay
            assert sorted(map(key, rows)) == sorted(map(key, want)), name
        assert len(rows) == len(want), name


def test_scoring_operators_on_odd_tables(spark):
    """Null and repeated doc_ids, very long texts, ties."""
    from fullgraph.llm import langid, mixing, toxicity

    rng = random.Random(12)
    long = prose(rng, 60_000)
    ids = [1, 1, None, 4, 5, 6]
    df = table(spark, [prose(rng, 20), prose(rng, 20), "a b", None, long, ""], ids=ids)
    labels = spark.createDataFrame([(1, 1, 0), (1, 1, 1), (5, 0, 0), (None, 1, 1), (6, None, None)], "doc_id long, quality int, toxic int")
    for rows in (langid.identify(spark, df).collect(), toxicity.classify(spark, df, labels).collect(), mixing.calibrated(spark, df).collect()):
        assert sorted(r.doc_id or -1 for r in rows) == [-1, 1, 1, 4, 5, 6]
    mixed = mixing.calibrated(spark, df).filter("doc_id = 5").first()
    assert mixed.n_tokens == 60_000
    drawn = [r.selected for r in mixing.calibrated(spark, table(spark, ["a b"] * 3, ids=[9, 9, 9]).withColumn("lang", __import__("pyspark").sql.functions.lit("en")).withColumn("source", __import__("pyspark").sql.functions.lit("a"))).collect()]
    assert len(set(drawn)) == 1  # repeated rows share one draw


def test_language_against_brute_force(spark):
    """The query's model and scores from plain dictionaries over the same hashed n-grams."""
    import math
    import zlib

    from fullgraph.llm import langid

    rng = random.Random(14)
    say = {"en": "the and of with that this have".split(), "fr": "le la les des pour avec être".split(), "de": "der die das und nicht über".split()}
    rows = [(i, " ".join(rng.choice(say[x]) for _ in range(rng.randint(1, 12))), x) for i, x in enumerate(rng.choice(sorted(say)) for _ in range(150))]
    df = spark.createDataFrame(rows, "doc_id long, text string, lang string")

    def grams(t):
        out = collections.Counter()
        t = langid.PAD + t.lower() + langid.PAD
        for at in range(len(t) - 2):
            h = 0
            for k in range(3):
                h = ((h ^ ord(t[at + k])) * 0x9E3779B1) & 0xFFFFFFFF
                out[(((h ^ (h >> 15)) * 0x85EBCA6B) & 0xFFFFFFFF) >> 17] += 1
        return out

    count = {x: collections.Counter() for x in say}
    for i, t, x in rows:
        if zlib.crc32(str(i).encode()) % 5:
            count[x] += grams(t)
    total = {x: sum(c.values()) + 0.5 * langid.BUCKETS for x, c in count.items()}
    got = {r.doc_id: r for r in langid.identify(spark, df).collect()}
    for i, t, _ in rows:
        s = {x: sum(n * math.log((count[x][b] + 0.5) / total[x]) for b, n in grams(t).items()) for x in say}
        best = max(s, key=s.get)
        top = sorted(s.values())
        if top[-1] - top[-2] > 1e-2:
            assert got[i].lang_pred == best
        assert abs(got[i].score - 1 / sum(math.exp(v - s[got[i].lang_pred]) for v in s.values())) < 1e-2
    many = langid.score_texts([t for _, t, _ in rows], np.zeros((langid.BUCKETS, 3), dtype=np.float32))
    assert many.shape == (150, 3) and not many.any()


def test_toxicity_against_brute_force(spark):
    """The query's verdicts from the fitted chain, text by text with dictionaries."""
    import math

    from fullgraph.llm import toxicity

    docs, labels = (spark.read.parquet(f"/root/testdata/sf0.01/{t}.parquet") for t in ("documents", "labels"))
    chain = toxicity.train(spark, docs, labels)
    got = {r.doc_id: r for r in toxicity.score(spark, docs, chain).collect()}
    for r in docs.collect():
        words = re.findall(r"[^\W\d_]+", (r.text or "").lower())
        n = max(len(words), toxicity.FULL // 2)
        value = []
        for f in chain.words:
            hits = sum(w == f for w in words) if f[-1] != "*" else sum(len(w) > len(f) - 1 and w.startswith(f[:-1]) for w in words)
            value.append(min(1.0, hits * toxicity.FULL / n) if f[-1] == "*" else float(hits > 0))
        p = []
        for w in chain.weights:
            z = sum(a * b for a, b in zip([*value, *p], w)) + w[-1]
            p.append(1 / (1 + math.exp(-max(-40, min(40, z)))))
        assert abs(got[r.doc_id][f"p_{chain.categories[-1]}"] - p[-1]) < 1e-9
        assert got[r.doc_id].is_toxic == (p[-1] >= 0.5)


def test_exact_dedup_compares_hits_only(spark):
    from pyspark.sql import functions as F

    from fullgraph.llm import exact_dedup

    df = table(spark, ["a b", "ab", "c", "d", "c ", "e"])
    hits = exact_dedup.exact_groups(spark, df).filter("group_size > 1")
    assert hits.count() == 4
    digests = df.select(exact_dedup.sha_key(exact_dedup.normal_text(F.col("text"))).alias("digest")).distinct()
    plan = exact_dedup.unequal_digests(spark, df, digests)._jdf.queryExecution().toString()
    assert "BroadcastHashJoin" in plan and "Python" not in plan and "Arrow" not in plan
    weak = lambda norm: F.unhex(F.lit("00"))  # noqa: E731  all digests are one
    assert exact_dedup.unequal_digests(spark, df, df.limit(1).select(weak(F.col("text")).alias("digest")), weak).count() == 1


def test_counters_add_up_in_a_tree(spark, monkeypatch):
    import pyarrow as pa

    from fullgraph.llm import jaccard_join

    rng = random.Random(15)
    docs = table(spark, [prose(rng, 30) for _ in range(40)]).repartition(9)
    first = docs.select("doc_id", "text").mapInArrow(jaccard_join._first_pass(4), "doc_id long, n long, set_key binary, part int, lane int, counts binary").cache()
    want = jaccard_join.count_table(first)
    monkeypatch.setattr(jaccard_join, "FAN_IN", 2)
    assert (jaccard_join.count_table(first) == want).all() and want.any() and pa is not None


def test_other_tokenizer_files_take_the_plain_call(spark, tmp_path):
    tokenizers = pytest.importorskip("tokenizers")
    import json

    from fullgraph.llm import packing

    assert packing.cut_is_known(packing.default_tokenizer())
    told = json.load(open(packing.default_tokenizer(), encoding="utf-8"))
    told["normalizer"] = None  # capitals stay
    path = str(tmp_path / "other.json")
    json.dump(told, open(path, "w", encoding="utf-8"))
    assert not packing.cut_is_known(path)
    text = "Some TEXT with Capitals 12"
    want = tokenizers.Tokenizer.from_file(path).encode(text, add_special_tokens=False).ids + [1]
    rows = sorted(packing.pack(spark, table(spark, [text]), path).collect(), key=lambda r: r.start)
    assert np.frombuffer(b"".join(bytes(r.ids) for r in rows), dtype="<u4").tolist() == want
    packing.write_buckets(packing.pack(spark, table(spark, [text, "a b c d e"])), str(tmp_path / "buckets"))
    back = spark.read.parquet(str(tmp_path / "buckets"))
    assert back.filter("length <> power(2, bucket)").count() == 0 and back.count() > 2


def test_pipeline(spark):
    pipeline = pytest.importorskip("corpus_pipeline")
    d = "/root/testdata/sf0.001"
    docs = spark.read.parquet(f"{d}/documents.parquet")
    rows = pipeline.run(spark, d).collect()
    ids = {r.doc_id for r in rows}
    assert 0 < len(ids) < docs.count()
    kept = docs.filter(docs.doc_id.isin(sorted(ids))).collect()
    norms = [re.sub("[\x20\x09-\x0d]", "", r.text) for r in kept]
    assert len(set(norms)) == len(norms)
    assert len(set(brute_components([r.text for r in kept], 5, 80).values())) <= len(kept)
    assert all(c == i for i, (_, c) in brute_components([r.text for r in kept], 5, 80).items())


# ---------------------------------------------------------------- chaining: recall


def edited(rng, words, share, vocabulary):
    out = []
    for w in words:
        r = rng.random()
        if r >= share:
            out.append(w)
        elif r < share * 0.6:
            out.append(rng.choice(vocabulary))
        elif r < share * 0.8:
            out += [w, rng.choice(vocabulary)]
    return out


def test_passage_recall_against_all_pairs(spark):
    """Planted pairs at several edit rates, half of them with fragments of the passage in smaller documents."""
    from fullgraph.llm import chaining

    rng = random.Random(77)
    vocabulary = [f"w{i}" for i in range(50000)]
    text = lambda n: [rng.choice(vocabulary) for _ in range(n)]
    fragments, pairs = [], []
    for share in (0.03, 0.05, 0.08, 0.10):
        for i in range(30):
            p = text(80)
            q = edited(rng, p, share, vocabulary)
            if i % 2:
                fragments += [text(15) + p[lo : lo + 30] + text(15) for lo in (0, 25, 50)]
            pairs.append((share, p, q, text(20) + p + text(20), text(20) + q + text(20)))
    texts = fragments + [t for x in pairs for t in x[3:]]
    got = {(r.doc_id, r.ref_doc_id): r for r in chaining.passages(spark, table(spark, [" ".join(t) for t in texts])).collect()}
    hits, asked = collections.Counter(), collections.Counter()
    for n, (share, p, q, a, b) in enumerate(pairs):
        same = chaining.common_subsequence(p, q)  # brute force: does the planted pair pass the operator's own thresholds?
        if same < chaining.MIN_WORDS or same < chaining.MIN_SHARE * max(len(p), len(q)):
            continue
        asked[share] += 1
        d = len(fragments) + 2 * n
        hits[share] += (d + 1, d) in got and got[d + 1, d].matched >= 40
    assert all(asked[s] >= 15 for s in asked) and all(hits[s] >= 0.9 * asked[s] for s in asked), (hits, asked)


def test_a_long_passage_whose_fragments_come_first(spark):
    from fullgraph.llm import chaining

    rng = random.Random(78)
    vocabulary = [f"w{i}" for i in range(50000)]
    text = lambda n: [rng.choice(vocabulary) for _ in range(n)]
    p = text(90)
    small = [text(9) + p[lo : lo + 30] + text(9) for lo in (0, 15, 30, 45, 60)]
    rows = chaining.passages(spark, table(spark, [" ".join(t) for t in [*small, text(20) + p + text(20), text(11) + p + text(7)]])).collect()
    assert [tuple(r) for r in rows] == [(6, 5, 11, 90, 20, 90, 90)]


def test_passes_split_the_seeds_of_every_word(spark):
    """A pass shuffles the seeds of its buckets only; together they are all seeds, each once."""
    import pyarrow as pa

    from fullgraph.llm import chaining

    rng = random.Random(82)
    batch = pa.RecordBatch.from_pydict({"doc_id": [0, 1], "text": [" ".join(str(rng.randrange(900)) for _ in range(3000)) for _ in range(2)]})

    def seeds(*turn):
        return [r for b in chaining._seeds(((4, 1),), 2048, *turn)(iter([batch])) for r in b.to_pylist()]

    key = lambda r: (r["bucket"], r["codes"], r["docs"], r["places"])
    split = [seeds(t, chaining.PASSES) for t in range(chaining.PASSES)]
    assert sorted(map(key, sum(split, []))) == sorted(map(key, seeds()))
    size = lambda rows: sum(len(r["codes"]) for r in rows)
    assert max(map(size, split)) < 0.6 * size(seeds())


def test_a_passage_whose_seeds_stand_in_smaller_documents_on_both_sides(spark):
    """All words of the passage stand in smaller documents, piece by piece, and again in one between the two that share the passage."""
    from fullgraph.llm import chaining

    rng = random.Random(81)
    vocabulary = [f"w{i}" for i in range(50000)]
    text = lambda n: [rng.choice(vocabulary) for _ in range(n)]
    p = text(60)
    q = [rng.choice(vocabulary) if i % 6 == 5 else w for i, w in enumerate(p)]  # runs of five equal words
    pieces = [p[i : i + 24] for i in range(0, 54, 18)]
    before, between = ([text(30) + x + text(30) for x in pieces] for _ in range(2))
    texts = [*before, text(20) + p + text(20), *between, text(11) + q + text(7)]
    got = {(r.doc_id, r.ref_doc_id): r for r in chaining.passages(spark, table(spark, [" ".join(t) for t in texts])).collect()}
    assert set(got) == {(7, 3)} and got[7, 3].matched == 50


def test_chaining_odd_tables(spark):
    from fullgraph.llm import chaining

    rng = random.Random(79)
    vocabulary = [f"w{i}" for i in range(5000)]
    p = " ".join(rng.choice(vocabulary) for _ in range(60))
    got = chaining.passages(spark, table(spark, [p, p, p, None, "x " + p], ids=[3, 3, None, 4, 9])).collect()
    assert [tuple(r) for r in got] == [(9, 3, 1, 60, 0, 60, 60)]


def test_hot_stretch_is_salted(spark, monkeypatch):
    from fullgraph.llm import chaining

    rng = random.Random(80)
    vocabulary = [f"w{i}" for i in range(5000)]
    p = " ".join(rng.choice(vocabulary) for _ in range(50))
    df = table(spark, [p] * 12)
    want = {tuple(r) for r in chaining.passages(spark, df).collect()}
    monkeypatch.setattr(chaining, "HOT", 2)
    assert {tuple(r) for r in chaining.passages(spark, df).collect()} == want == {(i, 0, 0, 50, 0, 50, 50) for i in range(1, 12)}


def test_chaining_finds_its_hot_stretches_without_a_shuffle_of_words(spark, monkeypatch):
    """The few hot stretches are broadcast: each join with them by a shuffle wrote all words once more."""
    from fullgraph.llm import chaining

    plans = []
    kept = chaining.stored

    def stored(session, df, name):
        if name == "passages":
            plans.append(df._jdf.queryExecution().optimizedPlan().toString())
        return kept(session, df, name)

    monkeypatch.setattr(chaining, "stored", stored)
    rng = random.Random(3)
    common = [f"w{rng.randint(0, 10**6)}" for _ in range(60)]
    docs = spark.createDataFrame([(i, " ".join(common + [f"x{i}"])) for i in range(4)], "doc_id long, text string")
    got = chaining.passages(spark, docs).collect()
    assert sorted((r.doc_id, r.ref_doc_id, r.matched) for r in got) == [(i, 0, 60) for i in (1, 2, 3)]
    assert len(plans) == 2 and all(p.count("strategy=broadcast") >= 4 for p in plans)


def test_chaining_decides_pairs_of_two_matches_and_runs_in_arrays():
    from fullgraph.llm import chaining

    rng = random.Random(4)
    for _ in range(300):
        m = sorted({(1, 0, rng.randint(0, 40), rng.randint(0, 40)) for _ in range(2)})
        if len(m) == 2:
            chained = len(chaining.chains([r[2:] for r in m], 4)) == 1
            assert bool(chaining.follows(np.array(m), np.array([0]), 4, chaining.GAP)[0]) == chained
        m = np.array([(rng.randint(0, 1), 0, rng.randint(0, 9), rng.randint(0, 9)) for _ in range(40)])
        t = chaining.thinned(m, 4)
        assert np.array_equal(t, np.unique(t, axis=0)) and {tuple(r) for r in t.tolist()} <= {tuple(r) for r in m.tolist()}

    def walk(a, b, i, j, step, run=3):  # word by word, all jumps tried
        inside = lambda u, v: 0 <= u < len(a) and 0 <= v < len(b)
        while True:
            while inside(i, j) and a[i] == b[j]:
                i, j = i + step, j + step
            for p, q in chaining.JUMPS:
                places = [(i + step * (p + r), j + step * (q + r)) for r in range(run)]
                if all(inside(u, v) and a[u] == b[v] for u, v in places):
                    i, j = places[0]
                    break
            else:
                return i, j

    for _ in range(2000):
        a, b = ([rng.randint(0, rng.choice((2, 9))) for _ in range(rng.randint(1, 14))] for _ in range(2))
        i, j, step = rng.randint(-1, len(a)), rng.randint(-1, len(b)), rng.choice((1, -1))
        if step > 0 and min(i, j) < 0:
            continue
        assert chaining.stretch(a, b, i, j, step) == walk(a, b, i, j, step)
