"""Decontamination, license scan, exact dedup, SimHash and passages against brute force, on small and awkward inputs."""

import hashlib
import random
import re

import numpy as np
import pytest
import xxhash
from pyspark.sql import functions as F

from contactscope.llm import components, decontaminate, exact_dedup, licenses, passages, queries, simhash, sql, wordhash
from tests.conftest import SF, same_as_sql

DOCS = "doc_id long, text string, lang string, source string, n_chars long"


def docs_of(spark, texts, schema=DOCS):
    return spark.createDataFrame([(i, t, None, "s", 0) for i, t in texts], schema)


AWKWARD = [(1, None), (2, ""), (3, " \n\t "), (4, "word"), (4, "word"), (5, "wo rd"), (None, "w o r d"), (6, "x" * 70_000), (7, "ä" * 3 + " b"), (8, "ÄB c 12_3"), (9, "a b c d e f g h i j k l m n o p q")]


@pytest.mark.parametrize("name", sorted(sql.ORACLES))
def test_query_equals_sql(spark, duck, name):
    same_as_sql(queries.queries()[name](spark, SF), duck, sql.ORACLES[name])


# --- decontamination

WORDS = re.compile("[^\x00-\x2f\x3a-\x60\x7b-\x7f]+")


def hits_by_force(texts, items, n=13):
    low = str.maketrans("ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")
    out = []
    for doc, text in texts:
        w = WORDS.findall((text or "").translate(low))
        hit, found = set(), set()
        for item, t in items:
            v = WORDS.findall((t or "").translate(low))
            if not v or item is None:
                continue
            k = min(n, len(v))
            grams = {tuple(v[i : i + k]) for i in range(len(v) - k + 1)}
            for i in range(len(w) - k + 1):
                if tuple(w[i : i + k]) in grams:
                    hit.update(range(i, i + k))
                    found.add(str(item))
        out.append((doc, len(w), len(hit), len(found), hashlib.sha256(",".join(sorted(found)).encode()).hexdigest(), bool(hit) and 20 * len(hit) >= len(w)))
    return sorted(out, key=str)


@pytest.mark.parametrize("most", [1, 7, 10**6])
def test_decontamination_equals_brute_force(spark, most):
    r = random.Random(2)
    words = ["a", "B", "cé", "d1", "e", "f"]
    text = lambda n: "".join(r.choice(words) + r.choice([" ", ", ", "\n", "_"]) for _ in range(n))
    items = [(i, text(r.choice([1, 3, 12, 13, 14, 30]))) for i in range(12)] + [(77, None), (78, "--"), (None, "a b"), (3, text(20))]
    texts = [(i, text(60) + (items[i % 12][1] or "") + text(50)) for i in range(25)] + AWKWARD
    bench = spark.createDataFrame(items, "item_id long, text string")
    got = decontaminate.digest(docs_of(spark, texts), bench, max_ngrams=most)
    assert got.columns == ["doc_id", "n_words", "n_hit", "n_items", "items_sha256", "contaminated"]
    assert sorted((tuple(x) for x in got.collect()), key=str) == hits_by_force(texts, items)


def test_decontamination_cuts_and_drops(spark):
    passage = " ".join(f"w{i}" for i in range(20))
    bench = spark.createDataFrame([(1, passage)], "item_id long, text string")
    docs = docs_of(spark, [(1, f"Before, {passage}. After"), (2, "clean text"), (3, None), (4, "long " * 1000 + passage)])
    cut = {r["doc_id"]: r["text"] for r in decontaminate.cut_spans(docs, bench).collect()}
    assert cut[1] == "Before, . After" and cut[2] == "clean text" and cut[3] is None
    assert sorted(r["doc_id"] for r in decontaminate.drop_contaminated(docs, bench).collect()) == [2, 3, 4]
    none = spark.createDataFrame([], "item_id long, text string")
    assert decontaminate.drop_contaminated(docs, none).count() == 4
    assert decontaminate.digest(docs.limit(0), bench).count() == 0


def test_extra_columns_with_clashing_names(spark):
    docs = docs_of(spark, [(1, "a b"), (2, "a b")]).withColumns({"n_words": F.lit(9), "hits": F.lit("x"), "items": F.lit("y"), "owner": F.lit(1), "fp": F.lit(2), "sha": F.lit("z")})
    bench = spark.createDataFrame([(1, "a b")], "item_id long, text string")
    assert {r["n_words"] for r in decontaminate.digest(docs, bench).collect()} == {2}
    clean = docs.union(docs_of(spark, [(3, "quite clean")]).withColumns({"n_words": F.lit(7), "hits": F.lit("u"), "items": F.lit("v"), "owner": F.lit(1), "fp": F.lit(2), "sha": F.lit("z")}))
    for most in (1, 10):
        bench = spark.createDataFrame([(1, "a b"), (2, "c d"), (3, "b a")], "item_id long, text string")
        assert [tuple(r) for r in decontaminate.drop_contaminated(clean, bench, max_ngrams=most).collect()] == [(3, "quite clean", None, "s", 0, 7, "u", "v", 1, 2, "z")]
        cut = decontaminate.cut_spans(clean, bench, max_ngrams=most)
        assert cut.columns == clean.columns and sorted((r["doc_id"], r["text"], r["hits"]) for r in cut.collect()) == [(1, "", "x"), (2, "", "x"), (3, "quite clean", "u")]
        found = decontaminate.scan(clean, bench, max_ngrams=most).collect()
        assert sorted((r["doc_id"], r["n_words"], r["hits"], r["items"]) for r in found) == [(1, 2, [0, 2], ["1"]), (2, 2, [0, 2], ["1"]), (3, 2, [], [])]
    assert exact_dedup.duplicates(docs).where("kept").count() == 1
    assert simhash.near_duplicates(docs).select("component_id").distinct().count() == 1


# --- exact dedup


def test_golomb_codes_round_trip():
    r = np.random.default_rng(1)
    for n, bits in ((0, 40), (1, 40), (5, 64), (1000, 40), (1000, 12), (3, 1)):
        span = 1 << (bits - 2) if bits > 2 else 2
        low = 2 * span
        v = np.sort(r.integers(0, span, n, dtype=np.uint64)) + np.uint64(low)
        code = exact_dedup.golomb_encode(v, low, span)
        assert np.array_equal(exact_dedup.golomb_decode(code, low), v)
    dense = np.sort(r.integers(0, 1 << 30, 20000, dtype=np.uint64))
    assert len(exact_dedup.golomb_encode(dense, 0, 1 << 30)) < 20000 * 2.6


def dedup_by_force(texts):
    groups = {}
    for i, t in texts:
        groups.setdefault(re.sub("[\x20\x09-\x0d]", "", t or ""), []).append((-len(t or ""), i is None, i or 0))
    out = []
    for i, t in texts:
        norm = re.sub("[\x20\x09-\x0d]", "", t or "")
        best = min(groups[norm])
        keep = None if best[1] else best[2]
        out.append((i, keep, len(groups[norm]), keep == i, hashlib.sha256(norm.encode()).hexdigest()))
    return sorted(out, key=str)


@pytest.mark.parametrize("bits", [1 << 16, 1 << 31])
def test_exact_dedup_equals_brute_force(spark, bits):
    r = random.Random(4)
    texts = AWKWARD + [(100 + i, "".join(r.choice("ab \n") for _ in range(r.randrange(6)))) for i in range(300)]
    got = exact_dedup.duplicates(docs_of(spark, texts).repartition(7), bits)
    assert sorted((tuple(x) for x in got.collect()), key=str) == dedup_by_force(texts)
    assert exact_dedup.duplicates(docs_of(spark, [])).count() == 0


# --- SimHash


def simhash_by_force(text, k=4):
    words = re.findall("[^\x20\x09-\x0d]+", re.sub("[A-Z]", lambda m: m[0].lower(), text or ""))
    if not words:
        return 0
    grams = [" ".join(words[i : i + k]) for i in range(len(words) - k + 1)] or [" ".join(words)]
    hs = [xxhash.xxh64_intdigest(g.encode(), 42) for g in grams]
    return sum(1 << b for b in range(64) if 2 * sum(h >> b & 1 for h in hs) > len(hs))


def components_by_force(codes, budget=4):
    up = list(range(len(codes)))

    def root(i):
        while up[i] != i:
            i = up[i]
        return i

    for i in range(len(codes)):
        for j in range(i):
            if bin(codes[i] ^ codes[j]).count("1") <= budget:
                a, b = root(i), root(j)
                up[max(a, b)] = min(a, b)
    return [root(i) for i in range(len(codes))]


def test_fingerprints_equal_the_definition():
    r = random.Random(6)
    texts = [t for _, t in AWKWARD] + [" ".join(r.choice(["Ab", "c", "É", "dd\n"]) for _ in range(r.randrange(40))) for _ in range(100)]
    for t in texts:
        assert simhash.simhash(None if t is None else t.encode()) == simhash_by_force(t)
    long = " ".join(str(i % 977) for i in range(400_000))
    assert simhash.simhash(long.encode()) == simhash_by_force(long)


def close_codes(r, n):
    codes = {0, (1 << 64) - 1}
    for _ in range(n):
        base = r.getrandbits(64)
        for _ in range(r.randrange(1, 12)):
            codes.add(base)
            for b in r.sample(range(64), r.randrange(0, 6)):
                base ^= 1 << b
    return sorted(codes)


@pytest.mark.parametrize("limit", [3, 10_000])
def test_trie_components_equal_brute_force(limit):
    r = random.Random(7)
    codes = close_codes(r, 40) + sorted(set(range(0, 300, 3)))
    codes = sorted(set(codes))
    got = simhash.trie_components(np.array(codes, np.uint64), np.zeros(len(codes), np.int64), 4, limit)
    assert got.tolist() == components_by_force(codes)


def test_trie_groups_stay_apart():
    codes = np.array([1, 3, 1, 3], np.uint64)
    got = simhash.trie_components(codes, np.array([0, 0, 5, 5]), 4)
    assert got.tolist() == [0, 0, 2, 2]


@pytest.mark.parametrize("blocks", [5, 6, 7])
def test_links_connect_like_all_pairs(spark, blocks):
    codes = close_codes(random.Random(8), 60)
    df = spark.createDataFrame([(c - (1 << 64) if c >= 1 << 63 else c,) for c in codes], "fp long")
    star = {r["u"] % (1 << 64): r["v"] % (1 << 64) for r in components.stars(simhash.links(df, 4, blocks)).collect()}
    roots = components_by_force(codes)
    groups, got = {}, {}
    for c, r in zip(codes, roots):
        groups.setdefault(r, set()).add(c)
    for c in codes:
        got.setdefault(star.get(c, c), set()).add(c)
    assert sorted(map(sorted, groups.values())) == sorted(map(sorted, got.values()))


def test_near_duplicates_query(spark):
    rows = queries.op6_simhash_dedup(spark, SF).collect()
    texts = {r["doc_id"]: r["text"] for r in spark.read.parquet(f"{SF}/documents.parquet").collect()}
    ids = sorted(texts)
    codes = [simhash_by_force(texts[i]) for i in ids]
    root = components_by_force(codes)
    want = {(i, f"{c:016x}", ids[r]) for i, c, r in zip(ids, codes, root)}
    assert {tuple(r) for r in rows} == want


def test_near_duplicates_of_awkward_rows(spark):
    got = {(r["doc_id"], r["component_id"]) for r in simhash.near_duplicates(docs_of(spark, AWKWARD)).collect()}
    assert {(1, 1), (2, 1), (3, 1), (4, 4)} <= got
    assert simhash.near_duplicates(docs_of(spark, [])).count() == 0


def test_components_of_a_long_chain(spark):
    edges = spark.createDataFrame([(i, i + 1) for i in range(200)] + [(7, 7), (500, 400)], "u long, v long")
    got = {r["u"]: r["v"] for r in components.stars(edges).collect()}
    assert got == {i: 0 for i in range(1, 201)} | {500: 400}


# --- passages


def test_exact_passages_are_found_and_clean_documents_are_not(spark):
    r = random.Random(9)
    fresh = lambda n: " ".join(f"{r.choice('abcdefgh')}{r.randrange(10**6)}" for _ in range(n))
    shared, fuzzy = fresh(51), fresh(120).split()
    edited = fuzzy.copy()
    for at in (30, 31, 75):
        edited[at] = "changed"
    del edited[100]
    texts = [(i, fresh(r.randrange(10, 90)) + " " + shared + " " + fresh(30)) for i in range(8)]
    texts += [(20, fresh(40) + " " + " ".join(fuzzy)), (21, " ".join(edited) + " " + fresh(25))]
    texts += [(30 + i, fresh(100)) for i in range(10)] + [(50, "is one. " * 10), (51, None), (52, ""), (53, fresh(60)), (None, fresh(80))]
    texts += [(54, texts[-2][1]), (55, fresh(30) + " " + " ".join(shared.split()[:40]))]
    got = passages.repeated_passages(docs_of(spark, texts)).collect()
    flagged = {r["doc_id"] for r in got} | {r["other_id"] for r in got}
    assert flagged == set(range(8)) | {20, 21, 53, 54}
    by_pair = {(r["doc_id"], r["other_id"]): r for r in got}
    one = by_pair[21, 20]
    assert one["other_start"] == 40 and one["start_word"] == 0 and one["end_word"] == 119 and one["matched"] == 116
    assert by_pair[54, 53]["kind"] == "copy"
    assert all((i, 0) in by_pair for i in range(1, 8))
    assert passages.repeated_passages(docs_of(spark, [])).count() == 0


def test_chains_equal_brute_force():
    r = random.Random(10)
    for _ in range(200):
        parts = []
        for _ in range(r.randrange(1, 9)):
            s = r.randrange(60)
            parts.append((s, s + r.randrange(5, 12), r.randrange(-10, 10)))
        parts = sorted(set(parts))
        score = {}
        for p in sorted(parts):
            best = float(p[1] - p[0])
            for q in sorted(parts):
                if q in score and q[1] <= p[0] + 4 and q[1] + q[2] <= p[0] + p[2] + 4 and q < p:
                    gap = passages.GAP_COST * ((p[0] - q[1]) + (p[0] + p[2] - q[1] - q[2]))
                    best = max(best, p[1] - p[0] + score[q] - gap)
            score[p] = best
        top = passages.chains(parts, 4, max_gap=10**6)[0]
        total = float(top[0][1] - top[0][0])
        for q, p in zip(top, top[1:]):
            total += p[1] - p[0] - passages.GAP_COST * ((p[0] - q[1]) + (p[0] + p[2] - q[1] - q[2]))
        assert total == pytest.approx(max(score.values()))


def test_common_words():
    a, b = np.array([1, 2, 3, 4, 5]), np.array([2, 9, 4, 5, 1])
    assert passages.common_words(a, b) == 3
    assert passages.common_words(a, a[:0]) == 0


@pytest.mark.parametrize(("times", "words", "gap"), [(3, 51, 30), (5, 51, 30), (2, 60, 34)])
def test_passages_between_different_words_are_found(times, words, gap):
    g = np.random.default_rng(times)
    for _ in range(20):
        same = g.integers(0, 1 << 32, (times, words))
        x, y = (np.concatenate([np.concatenate((p, g.integers(0, 1 << 32, gap))) for p in same]).astype(np.uint32) for _ in range(2))
        found = passages.passages(x, y)
        covered = np.zeros(len(x), bool)
        for xs, xe, ys, ye, equal in found:
            assert min(xe - xs, ye - ys) >= 50 and equal >= 0.8 * max(xe - xs, ye - ys)
            covered[xs:xe] = True
        assert all(covered[i * (words + gap) : i * (words + gap) + words].all() for i in range(times))


@pytest.mark.parametrize("repeats", [64, 65, 200])
def test_every_repeat_of_a_footer_is_found(repeats):
    g = np.random.default_rng(repeats)
    fresh = lambda n: g.integers(0, 1 << 32, n)
    footer = fresh(60)
    x = np.concatenate([np.concatenate((fresh(50), footer)) for _ in range(repeats)]).astype(np.uint32)
    y = np.concatenate((fresh(70), footer, fresh(70))).astype(np.uint32)
    found = passages.passages(x, y)
    assert all(any(s <= i * 110 + 50 and i * 110 + 110 <= e for s, e, *_ in found) for i in range(repeats))


def test_stray_seeds_do_not_hide_repeats():
    g = np.random.default_rng(3)
    fresh = lambda n: g.integers(0, 1 << 32, n)
    same = fresh(60)
    for at in range(0, 50, 5):
        x, y = (np.concatenate([same[at : at + 10 * stray]] + [np.concatenate((fresh(50), same)) for _ in range(n)]).astype(np.uint32) for n, stray in ((9, 1), (8, 0)))
        found = passages.passages(x, y)
        assert all(any(s <= 10 + i * 110 + 50 and 10 + i * 110 + 110 <= e for s, e, *_ in found) for i in range(9))


@pytest.mark.parametrize("most", [1, 7, 10**6])
def test_matches_are_all_pairs_of_equal_seeds(most):
    g = np.random.default_rng(most)
    x, y = (g.integers(0, 2, n).astype(np.uint32) for n in (300, 200))
    (hx, px), (hy, py) = passages.seeds(x), passages.seeds(y)
    want = sorted((int(a), int(b)) for a, s in zip(px, hx) for b, t in zip(py, hy) if s == t)
    got = passages.matches((hx, px), passages.by_hash((hy, py)), most)
    assert sorted((int(a), int(b)) for m in got for a, b in zip(*m)) == want


def test_exact_windows_are_those_of_the_definition():
    g = np.random.default_rng(8)
    same = g.integers(0, 1 << 32, 51).astype(np.uint32)
    docs = [np.concatenate((g.integers(0, 1 << 32, g.integers(0, 80)), same, g.integers(0, 1 << 32, 9))).astype(np.uint32) for _ in range(20)]
    seeds = [set(passages.seeds(d)[0].tolist()) for d in docs]
    shared = np.array(sorted(q for q in set().union(*seeds) if sum(q in o for o in seeds) > 1), np.uint64)
    inner = set(passages.exact_keys(same, shared).tolist())
    assert len(inner) == 2
    for x in docs:
        keys = set(passages.exact_keys(x, shared).tolist())
        assert inner <= keys and len(keys) <= len(x) - 49


def test_word_hashes_follow_the_words():
    r = random.Random(12)
    parts = ["a", "B", "é", "12", " ", "  ", "-", "\n", "_", "Zz", "東京"]
    texts = ["", " ", *("".join(r.choice(parts) for _ in range(r.randrange(40))) for _ in range(200)), "ab " * 150_000 + "x", "x" * 300_000]
    known = {}
    for t, hashes in zip(texts, wordhash.Hasher().texts([t.encode() for t in texts])):
        words = decontaminate.words_of(t.encode())
        assert len(words) == len(hashes)
        assert all(known.setdefault(w, h) == h for w, h in zip(words, hashes.tolist()))
    assert len(set(known.values())) == len(known)


def test_seeds_of_an_intact_run_are_seeds_in_every_text():
    g = np.random.default_rng(21)
    for _ in range(50):
        same = g.integers(0, 1 << 32, 50).astype(np.uint32)
        x, y = (np.concatenate((g.integers(0, 1 << 32, 30), same, g.integers(0, 1 << 32, 30))).astype(np.uint32) for _ in range(2))
        inner = [{(int(h), int(a)) for h, a in zip(*passages.seeds(t)) if 30 + 15 <= a <= 75 - 15} for t in (x, y)]
        assert inner[0] == inner[1] and inner[0]


@pytest.mark.parametrize("words", [50, 80])
def test_fuzzy_passages_of_two_texts(words):
    """A fifth of the words replaced at random places but the ends: the least identity, found nearly always."""
    g = np.random.default_rng(words)
    fresh = lambda n: g.integers(0, 1 << 32, n).astype(np.uint32)
    found = 0
    for _ in range(200):
        same = fresh(words)
        other = same.copy()
        other[1 + g.choice(words - 2, words // 5, replace=False)] = fresh(words // 5)
        found += bool(passages.passages(np.concatenate((fresh(60), same, fresh(60))), np.concatenate((fresh(33), other, fresh(60)))))
    assert found >= 0.9 * 200


def windows_of(words, n=50):
    return {tuple(words[i : i + n]) for i in range(len(words) - n + 1)}


def best_stretch(x, y, n=50):
    """Most equal words of any n words of both on one diagonal that begin and end with equal ones."""
    best = 0
    for d in range(n - len(x), len(y) - n + 1):
        s = max(0, -d)
        same = x[s : len(y) - d] == y[s + d : len(x) + d]
        ends = same[n - 1 :] & same[: len(same) - n + 1]
        if ends.any():
            equal = np.concatenate(([0], np.cumsum(same)))
            best = max(best, int((equal[n:] - equal[:-n])[ends].max()))
    return best


def test_passages_of_all_pairs(spark):
    """All pairs of texts by force: texts with 50 equal words in a row are linked, directly or to one that has these words; of those with 40 equal
    words in 50 on one diagonal, nine in ten at least; and every passage that is returned has the words that it claims."""
    docs = spark.read.parquet(f"{SF}/documents.parquet").collect()
    words = {r["doc_id"]: decontaminate.words_of((r["text"] or "").encode()) for r in docs}
    rows = queries.op8_repeated_passages(spark, SF).collect()
    linked = {d: {d} for d in words}
    for r in rows:
        linked[r["doc_id"]].add(r["other_id"])
        linked[r["other_id"]].add(r["doc_id"])
        a, b = words[r["doc_id"]][r["start_word"] : r["end_word"]], words[r["other_id"]][r["other_start"] : r["other_end"]]
        assert min(len(a), len(b)) >= 50 and r["matched"] >= 0.8 * max(len(a), len(b)) and r["identity"] == round(r["matched"] / max(len(a), len(b)), 6)
        ids = {w: i for i, w in enumerate(sorted({*a, *b}))}
        if max(len(a), len(b)) < 2000:
            assert r["matched"] <= passages.common_words(np.array([ids[w] for w in a]), np.array([ids[w] for w in b]))
    longer = [d for d in sorted(words) if len(words[d]) >= 50]
    holders = {}
    for d in longer:
        for w in windows_of(words[d]):
            holders.setdefault(w, []).append(d)
    shared = [h for h in holders.values() if len(h) > 1]
    assert shared
    for h in shared:
        assert any(all(x == y or y in linked[x] for y in h) for x in h)
    number = {w: i for i, w in enumerate(sorted({w for d in longer for w in words[d]}))}
    arrays = {d: np.array([number[w] for w in words[d]]) for d in longer}
    counts = {d: np.bincount(v, minlength=len(number)) for d, v in arrays.items()}
    want = got = 0
    for i, x in enumerate(longer):
        for y in longer[:i]:
            if np.minimum(counts[x], counts[y]).sum() >= 40 and best_stretch(arrays[x], arrays[y]) >= 40:
                want += 1
                got += y in linked[x] or bool(linked[x] & linked[y])
    assert want and got >= 0.9 * want


def test_passage_of_two_texts_between_scraps_of_it(spark):
    g = np.random.default_rng(31)
    fresh = lambda n: [f"w{v}" for v in g.integers(0, 10**9, n)]
    same = fresh(80)
    texts = [(0, fresh(30) + same[:40]), (3, same[40:] + fresh(30)), (1, fresh(20) + same), (2, same + fresh(20))]
    texts += [(10 + i, fresh(30) + same[i : i + 40]) for i in range(0, 40, 4)] + [(100 + i, fresh(30) + same[i : i + 40]) for i in range(0, 40, 4)]
    for part in (texts[:4], texts):
        pairs = {(r["doc_id"], r["other_id"]) for r in passages.repeated_passages(docs_of(spark, [(i, " ".join(t)) for i, t in part])).collect()}
        assert pairs == {(2, 1)}


def test_exact_passages_behind_strangers_are_found(spark):
    g = np.random.default_rng(4)
    fresh = lambda n: [f"w{v}" for v in g.integers(0, 10**9, n)]
    same = fresh(51)
    pieces = [fresh(40) + same[i : i + 20] + fresh(40) for i in range(32)]
    texts = [(i, " ".join(p)) for i, p in enumerate(pieces)] + [(1000 + i, " ".join(p)) for i, p in enumerate(fresh(40) + same[i : i + 20] + fresh(30) for i in range(32))]
    texts += [(i, " ".join(fresh(30) + same + fresh(20))) for i in (100, 200, 300)]
    pairs = {(r["doc_id"], r["other_id"]) for r in passages.repeated_passages(docs_of(spark, texts)).collect()}
    assert {(200, 100), (300, 100)} <= pairs <= {(200, 100), (300, 100), (300, 200)}


@pytest.mark.parametrize("strangers", [8, 30])
def test_variants_of_a_passage_behind_scraps_of_it_are_found(spark, strangers):
    """Two variants share 80 words but for a few, and no 50 in a row; the first documents of all their keys have only scraps of them."""
    g = np.random.default_rng(8)
    fresh = lambda n: [f"w{v}" for v in g.integers(0, 10**9, n)]
    same = fresh(80)
    other = [w if i % 20 != 10 else f"v{i}" for i, w in enumerate(same)]
    scraps = [fresh(30) + same[a : a + 30] + fresh(30) for a in range(0, 51, 10) for _ in range(strangers)]
    scraps += [fresh(30) + other[a : a + 30] + fresh(30) for a in range(0, 51, 10) for _ in range(strangers)]
    texts = [(i, " ".join(t)) for i, t in enumerate(scraps)]
    texts += [(5000, " ".join(fresh(20) + same + fresh(20))), (5001, " ".join(fresh(25) + other + fresh(15)))]
    pairs = {(r["doc_id"], r["other_id"]) for r in passages.repeated_passages(docs_of(spark, texts)).collect()}
    assert pairs == {(5001, 5000)}


def test_a_common_line_makes_no_pairs_of_all_that_have_it(spark, monkeypatch):
    """Sixty documents share a line of 20 words and nothing else but for two, which share 80 words around it, a few of them replaced."""
    g = np.random.default_rng(12)
    fresh = lambda n: [f"w{v}" for v in g.integers(0, 10**9, n)]
    line = fresh(20)
    same = fresh(30) + line + fresh(30)
    other = [w if i % 13 != 6 or 30 <= i < 50 else f"v{i}" for i, w in enumerate(same)]
    texts = [(i, fresh(60) + line + fresh(60)) for i in range(60)] + [(5000, fresh(20) + same + fresh(20)), (5001, fresh(25) + other + fresh(15))]
    written, stored = {}, passages.stored
    monkeypatch.setattr(passages, "stored", lambda df, name, *a: written.setdefault(name, stored(df, name, *a)) if name == "later" else stored(df, name, *a))
    pairs = {(r["doc_id"], r["other_id"]) for r in passages.repeated_passages(docs_of(spark, [(i, " ".join(t)) for i, t in texts])).collect()}
    assert pairs == {(5001, 5000)}
    assert written["later"].count() <= 1


def test_marks_of_the_words_around_a_key():
    """Stretches of 50 words around a key that differ in ten places share 29 marks at least; a word's further occurrences count by themselves, wherever the key stands."""
    g = np.random.default_rng(13)
    for words in (10**9, 3):
        for _ in range(50):
            same = g.integers(0, words, 50).astype(np.uint32)
            other, at = same.copy(), int(g.integers(0, 46))
            other[g.choice(np.setdiff1d(np.arange(50), np.arange(at, at + 5)), 10, replace=False)] = g.integers(2 * 10**9, 3 * 10**9, 10)
            x, y = (np.concatenate((g.integers(0, 10**9, a).astype(np.uint32), v, g.integers(0, 10**9, b).astype(np.uint32))) for a, v, b in ((60, same, 7), (3, other, 80)))
            key = np.array([7], np.uint64)
            mx, my = (passages.context_marks(v, key, np.array([a + at]), np.array([a + at]))[0] for v, a in ((x, 60), (y, 3)))
            assert len(np.unique(mx)) == len(mx) <= 94 and len(np.intersect1d(mx, my)) >= 29
            twice = passages.context_marks(np.concatenate((x, x)), key, np.array([60 + at]), np.array([60 + at + len(x)]))[0]
            assert len(np.intersect1d(twice, my)) >= 29


# --- licenses


def scanner():
    return licenses.Scanner(licenses.TEMPLATES, 3, 3, 0.8, licenses.SIGNS)


def confirmed(s, text):
    data = text.encode()
    return [v[0] for a, b in next(iter(s.blocks([data]))) for v in s.verdict(data[a:b]) if v[2]]


def test_license_blocks(spark):
    mit = licenses.TEMPLATES["MIT"]
    texts = [
        (1, "intro\nReleased under the MIT License.\nmore"),
        (2, mit),
        (3, mit.replace("free of charge", "at a price").replace("Software", "Program")),
        (4, "no cue at all " * 50),
        (5, None),
        (6, ""),
        (7, "Copyright of the moon belongs to nobody in particular and that is that"),
        (8, "Licensed under CC BY-NC 4.0.\nx\nLicensed under the Apache License, Version 2.0."),
        (9, "x. " * 2000 + "Licensed under the Apache License, Version 2.0. " + "y. " * 2000),
        (10, "Permission to use, copy, modify, and/or distribute it is none of ours"),
    ]
    rows = licenses.scan(docs_of(spark, texts).repartition(3)).collect()
    best = {r["doc_id"]: r for r in rows}
    assert set(best) == {1, 2, 3, 8, 9, 10}
    assert best[1]["license"].startswith("MIT") and best[1]["confirmed"] and not best[1]["missing"] and not best[1]["foreign"]
    assert texts[0][1][best[1]["match_start"] : best[1]["match_end"]] == "Released under the MIT License"
    assert best[2]["license"] == "MIT" and best[2]["covered"] == 1.0
    assert best[3]["license"] == "MIT" and best[3]["confirmed"] and "charge" in best[3]["missing"] and "program" in best[3]["foreign"]
    assert sorted(r["license"] for r in rows if r["doc_id"] == 8) == ["Apache-2.0 notice", "CC-BY-NC-4.0 notice"]
    assert best[9]["license"].startswith("Apache") and best[9]["confirmed"]
    assert best[10]["license"] == "ISC" and not best[10]["confirmed"]
    assert licenses.scan(docs_of(spark, [])).count() == 0


def test_all_licenses_of_a_text_are_reported():
    s, t = scanner(), licenses.TEMPLATES
    assert confirmed(s, "Licensed under CC BY-NC 4.0.\nx\nLicensed under the Apache License, Version 2.0.") == ["CC-BY-NC-4.0 notice", "Apache-2.0 notice"]
    assert confirmed(s, t["MIT"] + "\n" + t["Apache-2.0"]) == ["MIT", "Apache-2.0"]
    assert confirmed(s, " ".join([t["MIT notice"], t["GPL-3.0"], t["MIT notice"]] * 300)) == ["MIT notice", "GPL-3.0", "MIT notice"] * 300
    for name in t:
        assert confirmed(s, t[name]) == [name]
        words = t[name].split()
        lines = "\n".join(" # " + " ".join(words[i : i + 6]) for i in range(0, len(words), 6))
        assert confirmed(s, "before it\n" + lines.upper() + "\nafter it") == [name]
    r = random.Random(6)
    for _ in range(40):
        prose = " ".join("".join(r.choice("etaoinshrdlu") for _ in range(r.randrange(2, 9))) for _ in range(290))
        at = prose.index(" ", 800)
        for name in ("MIT notice", "BSD notice"):
            assert confirmed(s, f"{prose[:at]} {t[name]} {prose[at:]}") == [name]


def test_ordinary_phrases_are_no_license():
    s = scanner()
    for text in ("public domain", "in the public domain", "copyright notice", "the above copyright notice", "under the License", "subject to the terms of the license", "Released under the Foo License.", "This work is licensed under the GNU General Public License, version 9.", "warranties of any kind, express or implied"):
        assert confirmed(s, text) == [] == confirmed(s, f"It was said that {text} is what he wrote about.")


def test_differences_of_a_cut_notice():
    s, t = scanner(), licenses.TEMPLATES["GPL-3.0"]
    text = t[40:-35].replace("modify", "improve").encode()
    (a, b), = next(iter(s.blocks([text])))
    row, = s.verdict(text[a:b])
    words = [w.decode() for w in licenses.WORD.findall(t.lower().encode())]
    assert row[0] == "GPL-3.0" and not row[2] and row[6] == ["modify"] and row[9] == ["improve"]
    inside = len(words) - len(row[7]) - len(row[8])
    assert row[7] == words[: len(row[7])] and row[8] == words[len(words) - len(row[8]) :] and 20 < inside < 0.8 * len(words)
    assert row[3] == round((inside - 1) / len(words), 6)


def lcs_by_force(a, b):
    table = [[0] * (len(b) + 1) for _ in range(len(a) + 1)]
    for i, x in enumerate(a):
        for j, y in enumerate(b):
            table[i + 1][j + 1] = table[i][j] + 1 if x == y else max(table[i][j + 1], table[i + 1][j])
    return table[-1][-1]


def test_common_subsequence_equals_brute_force():
    r = random.Random(14)
    for _ in range(100):
        a, b = ([r.randrange(5) for _ in range(r.randrange(1, 20))] for _ in range(2))
        pairs = licenses.common(np.array(a), np.array(b))
        assert len(pairs) == lcs_by_force(a, b) and all(a[i] == b[j] for i, j in pairs) and pairs == sorted(pairs)
        assert all(p[0] < q[0] and p[1] < q[1] for p, q in zip(pairs, pairs[1:]))


def test_license_query_equals_brute_force(spark):
    """Blocks by word triples, reductions by compressing anew, and equal and different words by another alignment, over all documents."""
    import zstandard

    docs = {r["doc_id"]: (r["text"] or "").encode() for r in spark.read.parquet(f"{SF}/documents.parquet").collect()}
    rows = queries.op4_license_scan(spark, SF).collect()
    triples = lambda data: [tuple(w) for w in zip(*(licenses.PLAIN_WORD.findall(data.lower())[k:] for k in range(3)))]
    known = {t for v in licenses.TEMPLATES.values() for t in triples(v.encode())}
    hit = {d for d, data in docs.items() if known & set(triples(data))}
    assert hit == {r["doc_id"] for r in rows} and hit
    for r in rows:
        block = docs[r["doc_id"]][r["start_byte"] : r["end_byte"]]
        plain = lambda data: b" ".join(licenses.WORD.findall(data.lower()))
        size = lambda name: len(zstandard.ZstdCompressor(level=3, dict_data=zstandard.ZstdCompressionDict(plain(licenses.TEMPLATES[name].encode()), dict_type=zstandard.DICT_TYPE_RAWCONTENT) if name else None, write_content_size=False, write_dict_id=False).compress(plain(block)))
        gains = sorted(((1 - size(k) / size(None), k) for k in licenses.TEMPLATES), key=lambda g: (-g[0], g[1]))
        assert [k for _, k in gains[:3]] == r["ranking"] and round(dict((k, g) for g, k in gains)[r["license"]], 6) == r["reduction"]
        template = [w.decode() for w in licenses.WORD.findall(licenses.TEMPLATES[r["license"]].lower().encode())]
        match = [w.decode() for w in licenses.WORD.findall(docs[r["doc_id"]][r["match_start"] : r["match_end"]].lower())]
        inner = template[len(r["missing_before"]) : len(template) - len(r["missing_after"])]
        assert template == r["missing_before"] + inner + r["missing_after"]
        equal = lcs_by_force(inner, match)
        assert equal == len(inner) - len(r["missing"]) == len(match) - len(r["foreign"]) and round(equal / len(template), 6) == r["covered"]
        assert r["confirmed"] == (r["covered"] >= 0.8 and set(licenses.SIGNS.get(r["license"], [])) <= set(match))


def test_license_ranking_is_by_reduction():
    s = scanner()
    for name in ("MIT", "Apache-2.0", "GPL-3.0", "BSD-3-Clause", "MPL-2.0"):
        order = s.reductions(s.words[name])
        assert order == sorted(order, key=lambda x: (-x[0], x[1])) and order[0][1] == name


def test_every_license_line_of_the_documents_is_reported(spark):
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    want = {r["doc_id"] for r in docs.where(F.col("text").rlike("(?i)licensed under|released under the MIT")).collect()}
    got = {r["doc_id"] for r in queries.op4_license_scan(spark, SF).where("confirmed").collect()}
    assert want <= got
