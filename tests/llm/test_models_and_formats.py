"""Packing, chat, WARC, language, toxicity and the pipeline: round trips, brute force and held-out accuracy."""

import hashlib
import random
import zlib

import numpy as np
import pytest
from pyspark.sql import functions as F

import corpus_pipeline
from contactscope.llm import chat, language, packing, queries, toxicity, warc
from contactscope.llm.common import pieces, table, without_ids
from tests.conftest import SF
from tests.llm.test_text_operators import AWKWARD, DOCS, components_by_force, dedup_by_force, docs_of, hits_by_force, simhash_by_force

# --- packing


def check_packing(rows, ids_of, length=2048):
    """Every document's ids once, in order; sequences gapless from 0 and full but for the last."""
    by_doc, by_seq = {}, {}
    for r in rows:
        by_doc.setdefault((r["doc_id"], r["doc_tokens"]), []).append(r)
        by_seq.setdefault(r["sequence_id"], []).append(r)
    for (doc, n), own in by_doc.items():
        own.sort(key=lambda r: r["start"])
        at = 0
        for r in own:
            assert r["start"] == at
            at += r["length"]
        assert at == n == len(ids_of[doc])
        for r in own:
            assert r["ids_crc32"] == zlib.crc32(np.array(ids_of[doc][r["start"] : r["start"] + r["length"]], "<u4").tobytes())
    for k, own in by_seq.items():
        own.sort(key=lambda r: r["offset"])
        at = 0
        for r in own:
            assert r["offset"] == at
            at += r["length"]
        assert at == length or k == max(by_seq) and at < length
    assert sorted(by_seq) == list(range(len(by_seq)))


@pytest.fixture(scope="module")
def exact_encoder():
    import public_tokenizers

    return packing.Encoder(public_tokenizers.path("byte_bpe_50k.json"), None)


def test_packing_of_all_documents(spark, exact_encoder):
    docs = table(spark, SF, "documents")
    ids = {r["doc_id"]: [*exact_encoder.ids(r["text"] or "").tolist(), 1] for r in docs.collect()}
    rows = queries.op1_mixture_packing(spark, SF).collect()
    assert {r["doc_id"] for r in rows} == set(ids)
    check_packing(rows, ids)


@pytest.mark.parametrize("weights", [None, {"a": 1.0, "b": 1.0, "c": 6.0}, {"a": 0.0, "b": 1.0}])
def test_packing_keeps_the_mixture(spark, exact_encoder, weights):
    r = random.Random(1)
    texts = [(i, " ".join(r.choice(["one", "two", "ünf"]) for _ in range(r.choice([0, 3, 400, 3000]))), "aabbbc"[i % 6]) for i in range(90)]
    df = spark.createDataFrame([(i, t, None, s, 0) for i, t, s in texts], DOCS).repartition(5)
    rows = packing.pack(df, weights=weights).collect()
    check_packing(rows, {i: [*exact_encoder.ids(t).tolist(), 1] for i, t, _ in texts})
    total = {}
    for x in rows:
        total[x["source"]] = total.get(x["source"], 0) + x["length"]
    shares = weights or total
    if min(shares.get(s, 0) for s in total) == 0:
        return
    whole = sum(shares.values())
    for s in total:  # no prefix is off the target by more than a cell for each queue, as long as no queue has run dry
        served = 0
        for x in sorted(rows, key=lambda x: (x["sequence_id"], x["offset"])):
            at = x["sequence_id"] * 2048 + x["offset"] + x["length"]
            if x["source"] == s:
                served += x["length"]
            if all(at * shares[q] / whole + 4 * 512 < total[q] for q in total):
                assert abs(served - at * shares[s] / whole) <= 512 * (len(total) + 1)


def test_packing_of_many_sources(spark, exact_encoder):
    """More sources than queues: those without a weight share queues, and every id still has its place."""
    r = random.Random(4)
    texts = [(i, " ".join(r.choice(["one", "two"]) for _ in range(r.choice([0, 5, 900]))), f"host{i}" if i % 3 else "main") for i in range(60)]
    df = spark.createDataFrame([(i, t, None, s, 0) for i, t, s in texts], DOCS).repartition(4)
    for weights in (None, {"main": 3.0}):
        rows = packing.pack(df, weights=weights, max_queues=5).collect()
        check_packing(rows, {i: [*exact_encoder.ids(t).tolist(), 1] for i, t, _ in texts})
        assert {(r["doc_id"], r["source"]) for r in rows} == {(i, s) for i, _, s in texts}


def test_rota_positions_are_a_permutation():
    r = random.Random(3)
    for _ in range(20):
        totals = [r.randrange(0, 20_000) for _ in range(r.randrange(1, 7))]
        rota = packing.Rota(totals, [r.random() for _ in totals] if r.random() < 0.5 else None)
        spans = []
        for q, t in enumerate(totals):
            cells = np.arange((t + 511) // 512)
            for c, p in zip(cells, rota.positions(q, cells)):
                spans.append((int(p), int(p) + min(512, t - 512 * int(c))))
        spans.sort()
        assert not spans or spans[0][0] == 0
        assert all(a[1] == b[0] for a, b in zip(spans, spans[1:])) and (spans[-1][1] if spans else 0) == sum(totals)


def test_fast_ids_equal_the_tokenizer(exact_encoder):
    import public_tokenizers

    fast = packing.Encoder(public_tokenizers.path("byte_bpe_50k.json"), public_tokenizers.path("byte_bpe_50k.tiktoken"))
    r = random.Random(5)
    plain = [chr(c) for c in range(0x250)]
    texts = [c for c in plain] + [a + c + b for c in plain for a, b in (("a", "b"), (" ", " "), ("1", "'s"), ("\n", "\t"))]
    texts += ["".join(r.choice(plain) for _ in range(50)) for _ in range(500)] + ["".join(r.choice("ab  \n\n'sé1<|>") for _ in range(80)) for _ in range(500)]
    texts += ["a <|endoftext|> b", "<|endoftext|>" * 3, "<|endoftext", "日本語 テキスト", "　x y", "x" * 3000, " " * 3000]
    for t in texts:
        assert fast.ids(t).tolist() == exact_encoder.ids(t).tolist()


def test_packing_of_awkward_rows(spark, exact_encoder):
    rows = packing.pack(docs_of(spark, [(i, t) for i, t in AWKWARD if i not in (4, None)])).collect()
    check_packing(rows, {i: [*exact_encoder.ids(t or "").tolist(), 1] for i, t in AWKWARD})
    assert packing.pack(docs_of(spark, [])).count() == 0
    twice = packing.pack(docs_of(spark, [(4, "word"), (4, "word"), (None, "x")]).withColumn("base", F.lit(1)).withColumn("part", F.lit("z")))
    assert sorted(((r["doc_id"] or 0, r["length"]) for r in twice.collect())) == [(0, 2), (4, 2), (4, 2)]


# --- chat

TURNS = "conv_id long, turn long, role string, text string"


def test_prefix_expansion(spark):
    rows = [(1, 0, "system", "s"), (1, 1, "user", "<|turn|>user\n[x]%3C%25"), (1, 2, "assistant", "a1\n"), (1, 3, "user", None), (1, 4, "assistant", "%5B<|end|>"), (1, 5, "user", "tail")]
    got = chat.expand(spark.createDataFrame(rows, TURNS)).orderBy("example").collect()
    assert [r["has_target"] for r in got] == [True, True, False]
    assert got[1]["formatted"].startswith(got[0]["formatted"]) and got[2]["formatted"].startswith(got[1]["formatted"])
    assert got[0]["formatted"].count("<|turn|>") == 3 and got[2]["formatted"].count("<|end|>") == 6
    masked = got[1]["formatted"][got[1]["loss_start"] - 1 :][: got[1]["loss_chars"]]
    assert masked == "%255B%3C|end|>"


def chat_by_force(rows):
    convs = {}
    for c, turn, role, text in rows:
        convs.setdefault(c, []).append((turn is not None, turn or 0, role or "", text or ""))
    out = {}
    for c, turns in convs.items():
        turns.sort()
        loss = "".join(t[3] for t in turns if t[2] == "assistant")
        flat = "".join(f"{t[2]}\n{t[3]}\n" for t in turns)
        out[c] = (len(turns), hashlib.sha256(flat.encode()).hexdigest(), len(loss), hashlib.sha256(loss.encode()).hexdigest())
    return out


def test_chat_digest_of_awkward_turns(spark):
    r = random.Random(2)
    parts = ["%", "<", "[", "<|end|>", "<|turn|>", "</s>[INST]", "%3C", "%25", "\n", "é", "𝄞", "x", "%0A"]
    rows = [(c, t, r.choice(["user", "assistant", "system", "a\n%0A<b", None]), r.choice([None, "", "".join(r.choice(parts) for _ in range(9))])) for c in range(40) for t in range(r.randrange(1, 7))]
    rows += [(None, 0, "assistant", "x"), (None, None, "user", "y"), (50, 0, "user", "a"), (50, 0, "user", "a"), (51, 0, "assistant", "long " * 100_000)]
    df = spark.createDataFrame(rows, TURNS).withColumns({"marked": F.lit(1), "turns": F.lit(2)})
    got = {r["conv_id"]: (r["n_turns"], r["turns_sha256"], r["loss_chars"], r["loss_sha256"]) for r in chat.digest(df).collect()}
    assert got == chat_by_force(rows)
    assert chat.digest(df.limit(0)).count() == 0


def test_chat_runs_no_python(spark):
    plan = chat.digest(chat.with_probe(spark, table(spark, SF, "conversations")))._jdf.queryExecution().executedPlan().toString()
    assert "Python" not in plan and "Arrow" not in plan and plan.count("Exchange") == 1


# --- WARC

PAGES = "page_id long, url string, html string"


def pages_by_force(rows, least=0):
    import base64

    first = {}
    for i, _, h in rows:
        if i is not None:
            first[h or ""] = min(first.get(h or "", i), i)
    out = []
    for i, _, h in rows:
        data = (h or "").encode()
        f = first.get(h or "")
        other = f if len(data) >= least and f is not None and f != i else None
        out.append((i, len(data), base64.b32encode(hashlib.sha1(data).digest()).decode(), "response" if other is None else "revisit", other))
    return sorted(out, key=str)


@pytest.mark.parametrize("least, chunk", [(0, 1 << 18), (4, 7)])
def test_warc_round_trip(spark, least, chunk):
    rows = [(1, "http://a/", "x"), (2, None, "x"), (3, "u", None), (4, "ü \r\n", ""), (5, "u", "é" * 500), (6, "u", "é" * 500), (6, "u", "é" * 500), (7, "u", "WARC/1.1\r\n\r\n"), (None, "u", "solo"), (8, "u", "ab" * 40_000)]
    df = spark.createDataFrame(rows, PAGES).withColumn("sha1", F.lit("clash")).withColumn("first", F.lit(1)).repartition(3)
    chunks = warc.write_archives(df, least, chunk)
    assert chunks.agg(F.max(F.length("data"))).first()[0] <= max(chunk, 600)
    got = warc.read_records(chunks)
    assert sorted((tuple(r) for r in got.select("page_id", "payload_bytes", "payload_digest", "record_type", "refers_to").collect()), key=str) == pages_by_force(rows, least)
    assert warc.digest(df.limit(0)).count() == 0


@pytest.mark.parametrize("bits", [6, 27])
def test_records_across_parts_of_a_file(spark, bits):
    """Records that lie across the parts of a file that two tasks read, and a table of digest bits so small that all are suspects."""
    rows = [(i, "u", f"{i % 40}" * (3000 + i)) for i in range(300)] + [(1000 + i, "u", f"{i % 40}" * (3000 + i)) for i in range(0, 300, 3)]
    before = spark.conf.get("spark.sql.files.maxPartitionBytes")
    chunks = warc.write_archives(spark.createDataFrame(rows, PAGES).repartition(3), 0, 64, bits)
    try:
        spark.conf.set("spark.sql.files.maxPartitionBytes", "4k")
        got = warc.read_records(chunks)
        assert sorted((tuple(r) for r in got.select("page_id", "payload_bytes", "payload_digest", "record_type", "refers_to").collect()), key=str) == pages_by_force(rows)
    finally:
        spark.conf.set("spark.sql.files.maxPartitionBytes", before)


def test_archive_is_a_warc_file(spark):
    rows = [(i, f"http://h/{i}", f"<p>{i}</p>" * 2000) for i in range(5)]
    chunks = warc.write_archives(spark.createDataFrame(rows, PAGES).coalesce(1), 0, 1000)
    data = b"".join(warc.archive_bytes(chunks, chunks.first()["archive_id"]))
    seen = 0
    while data:
        head, _, data = data.partition(b"\r\n\r\n")
        assert head.startswith(b"WARC/1.1\r\nWARC-Type: response")
        n = int(next(x for x in head.split(b"\r\n") if x.startswith(b"Content-Length")).split(b": ")[1])
        assert data[:n].decode() == rows[seen][2] and data[n : n + 4] == b"\r\n\r\n"
        data, seen = data[n + 4 :], seen + 1
    assert seen == 5
    joined = warc.payload_chunks(chunks).where("page_id = 3").orderBy("chunk_no").collect()
    assert b"".join(bytes(r["data"]) for r in joined).decode() == rows[3][2]


def test_broken_archive_is_noticed(spark):
    chunks = warc.write_archives(spark.createDataFrame([(1, "u", "abc" * 100)], PAGES), 0, 50)
    with pytest.raises(Exception, match="cut short"):
        warc.read_records(chunks.where("chunk_no <> 2")).collect()


# --- language


def test_gradients_equal_differences():
    """Numerical gradients on windows that hold several words, a gap between two scripts and the end of a text."""
    net = language.Network(["a", "b", "c"], hidden=3, seed=1)
    for k in net.p:
        net.p[k] = net.p[k].astype(np.float64)
    texts = [b"ab c, ab", "é".encode(), "a я東b".encode()]
    data, starts, sizes, _ = language._padded(texts, 12)
    rows, target = language.laid_out(data, starts, 12), np.array([0, 1, 2])
    _, g = net.gradients(rows, sizes, target)
    r = np.random.default_rng(2)
    for k, v in net.p.items():
        cells = [tuple(r.integers(0, s) for s in v.shape) for _ in range(4)] if k[-1] != "W" else [(c, r.integers(0, v.shape[1])) for c in b"abc, " + "я".encode()]
        for c in cells:
            old = v[c]
            v[c] = old + 1e-5
            up, _ = net.gradients(rows, sizes, target)
            v[c] = old - 1e-5
            down, _ = net.gradients(rows, sizes, target)
            v[c] = old
            assert g[k][c] == pytest.approx((up - down) / 2e-5, abs=1e-5)


@pytest.fixture(scope="module")
def sf001():
    return "/root/testdata/sf0.01"


def test_language_held_out_accuracy(spark, sf001):
    truth = {r["doc_id"]: r["lang"] for r in table(spark, sf001, "documents").collect()}
    rows = queries.op9_language_id(spark, sf001).collect()
    assert {r["doc_id"] for r in rows} == set(truth)
    assert all(r["held_out"] == (zlib.crc32(str(r["doc_id"]).encode()) % 3 == 1) and 0 <= r["score"] <= 1 for r in rows)
    held = [r for r in rows if r["held_out"] and truth[r["doc_id"]] and r["lang_pred"] != "und"]
    assert np.mean([r["lang_pred"] == truth[r["doc_id"]] for r in held]) >= 0.98


def test_language_of_awkward_rows(spark, sf001):
    net = language.fit(table(spark, sf001, "documents"))
    rows = {r["doc_id"]: r for r in language.predict(docs_of(spark, [*AWKWARD, (20, "123 _ !?"), (21, "É"), (22, "the and of " * 200_000)]), net).collect()}
    assert all(rows[i]["lang_pred"] == "und" and rows[i]["score"] == 0 for i in (1, 2, 3, 20))
    assert rows[21]["lang_pred"] in net.languages and rows[22]["lang_pred"] == "en"
    assert language.fit(docs_of(spark, AWKWARD)) is None
    assert {r["lang_pred"] for r in language.digest(docs_of(spark, AWKWARD)).collect()} == {"und"}
    assert net.positions(b"the, 12").shape == (7, len(net.languages))
    labels = [r["doc_id"] for r in language.accepted(docs_of(spark, [(1, None), (2, "the and"), (3, "!")]), net).collect()]
    assert labels == [2]


def test_labelling_equals_the_training_pass():
    net = language.Network(["a", "b", "c"], hidden=5)
    texts = [b"abc de", "éfé 12".encode(), b"x"]
    data, starts, sizes, _ = language._padded(texts, language.SPAN)
    rows = language.laid_out(data, starts, 32)
    both = np.concatenate([net._taped(d, rows)[0] for d in "fb"], axis=2) @ net.p["V"] + net.p["b"]
    prob = np.exp(both) / np.exp(both).sum(axis=2, keepdims=True)
    for i, t in enumerate(texts):
        assert np.allclose(net.positions(t), prob[language.LEAD : language.LEAD + len(t), i], atol=1e-5)
        assert np.allclose(net.pooled(texts)[i], net.positions(t).mean(axis=0), atol=1e-5)


def test_windows_hold_whole_code_points_and_every_byte_once():
    r = random.Random(5)
    for _ in range(100):
        text = "".join(r.choice(["a", " ", "é", "東", "𝄞"]) for _ in range(r.randrange(1, 400))).encode()
        data, starts, sizes, owner = language._padded([b"zz", text], 40)
        mine = [(s, n) for s, n, o in zip(starts, sizes, owner) if o == 1]
        parts = [data[s : s + n].tobytes() for s, n in mine]
        assert b"".join(parts) == text and max(map(len, parts)) <= 43 and all(p.decode() for p in parts)
        rows = language.laid_out(data, np.array([s for s, _ in mine]), 43)
        for row, p in zip(rows, parts):
            assert row.tobytes().decode() and row[language.LEAD : language.LEAD + len(p)].tobytes() == p


def test_state_runs_across_words_and_windows():
    """A label depends on the word before it, on both sides of a window's edge, and not on what else is read with the text."""
    net = language.Network(["a", "b"], hidden=6)
    edge = b"x" * (language.SPAN - 4)
    one, two = net.positions(b"aaa bbb"), net.positions(b"ccc bbb")
    assert not np.allclose(one[4:], two[4:], atol=1e-4)
    one, two = net.positions(edge + b"aaa bbb"), net.positions(edge + b"ccc bbb")
    assert not np.allclose(one[-3:], two[-3:], atol=1e-4)
    texts = [b"one two", "東京都に住んでいます。".encode() * 100, b"", b"12 -", b"k" * 3000]
    alone = [language.read(net, [t])[0] for t in texts]
    assert alone == language.read(net, texts) == language.read(net, texts[::-1])[::-1]
    assert alone[2] == alone[3] == ("und", 0.0)


def test_unspaced_scripts_are_told_apart():
    r = random.Random(7)
    text = lambda low: "".join(chr(low + r.randrange(60)) for _ in range(300)).encode()
    lows = (0x4E00, 0x0E01, 0x0410)
    net = language.Network(["a", "b", "c"], hidden=8)
    net.fit([text(low) for low in lows for _ in range(10)], np.repeat([0, 1, 2], 10), steps=60)
    assert [language.read(net, [text(low)])[0][0] for low in lows] == ["a", "b", "c"]


# --- toxicity


def test_toxicity_held_out(spark):
    sf = "/root/testdata/sf0.1"
    truth = {r["doc_id"]: r["toxic"] for r in table(spark, sf, "labels").collect()}
    rows = queries.op10_toxicity(spark, sf).collect()
    held = [(r["predicted"], truth[r["doc_id"]]) for r in rows if r["held_out"] and r["doc_id"] in truth]
    caught = np.mean([p for p, t in held if t == 1])
    wrong = np.mean([p for p, t in held if t == 0])
    # about a twelfth of the toxic labels there mark texts without any such word, and a fiftieth of the others have some
    assert caught > 0.85 and wrong < 0.04
    assert all(0 <= r["score"] <= 1 and r["predicted"] == int(r["score"] >= 0.7) for r in rows)


def test_toxicity_of_awkward_rows(spark):
    docs = docs_of(spark, [*AWKWARD, *[(100 + i, "nasty awful words" if i % 3 == 0 else "kind words here") for i in range(60)]])
    labels = spark.createDataFrame([(100 + i, 1, 1 if i % 3 == 0 else 0) for i in range(60)] + [(100, 1, None), (None, 1, 1), (101, 0, 0), (100, 0, 0)], "doc_id long, quality int, toxic int")
    got = {r["doc_id"]: r["predicted"] for r in toxicity.digest(docs, labels).collect()}
    assert all(got[100 + i] == int(i % 3 == 0) for i in range(60)) and got[1] == got[2] == 0
    assert toxicity.digest(docs, labels.limit(0)).agg(F.max("score")).first()[0] < 1e-9
    assert toxicity.digest(docs.limit(0), labels).count() == 0


def test_toxicity_of_repeated_ids(spark):
    """A document of several texts is learned from with all their words, in whatever order its rows come."""
    rows = [(i, "nasty words" if i % 3 == 0 else "kind words", None, "s", 0) for i in range(60)] + [(i, "awful things" if i % 3 == 0 else "good things", None, "s", 0) for i in range(60)]
    labels = spark.createDataFrame([(i, 1, 1 if i % 3 == 0 else 0) for i in range(60)], "doc_id long, quality int, toxic int")
    made = [toxicity.fit(spark.createDataFrame(r, DOCS), labels) for r in (rows, rows[::-1])]
    assert made[0].weights == made[1].weights and made[0].bias == made[1].bias and made[0].weights
    few = toxicity._gathered(spark.createDataFrame(rows, DOCS), 7)
    assert len(few) == 7 and all(len(f) > len(toxicity.document_features(b"nasty words")) for f in few)


def test_non_negative_risk_survives_many_steps():
    r = np.random.default_rng(1)
    pos = [np.unique(np.append(r.integers(100, 1000, 20), 7)) for _ in range(40)]
    unl = [np.unique(r.integers(100, 1000, 20)) for _ in range(200)] + pos[:20]
    m = toxicity.train(pos, unl, 0.1, steps=2000)
    assert m.weights[7] > 1 and m.bias < 0


# --- pipeline and helpers


def test_pieces_join_to_the_text():
    for text in (b"", b"abc", b"a b " * 10, b"x" * 50, b"ab cd\nef gh ij kl mn"):
        for size in (1, 3, 7, 100):
            assert b"".join(pieces(text, size)) == text


def test_without_ids(spark):
    df = spark.createDataFrame([(1, "a"), (None, "b"), (2, "c"), (2, "c")], "doc_id long, text string")
    assert sorted(r["text"] for r in without_ids(df, df.where("doc_id = 2").select("doc_id")).collect()) == ["a", "b"]


def test_pipeline_stages_equal_brute_force(spark):
    docs = table(spark, SF, "documents")
    kept = []
    for name, stage in corpus_pipeline.STAGES[:-1]:
        after = stage(spark, docs, SF)
        assert after.columns == docs.columns
        before = {r["doc_id"]: r["text"] for r in docs.collect()}
        got = {r["doc_id"] for r in after.collect()}
        if name == "exact_dedup":
            want = {r[0] for r in dedup_by_force(sorted(before.items())) if r[3]}
        elif name == "simhash_dedup":
            ids = sorted(before)
            roots = components_by_force([simhash_by_force(before[i]) for i in ids])
            want = {ids[r] for r in roots}
        elif name == "decontamination":
            items = [tuple(r) for r in table(spark, SF, "benchmark").select("item_id", "text").collect()]
            want = {r[0] for r in hits_by_force(sorted(before.items()), items) if not r[5]}
        else:
            want = got
            assert len(got) >= 0.99 * len(before)
        assert got == want
        kept.append(len(got))
        docs = after
    assert kept == sorted(kept, reverse=True) and kept[-1] < kept[0]
    rows = corpus_pipeline.run(spark, SF).collect()
    assert {r["doc_id"] for r in rows} == {r["doc_id"] for r in docs.collect()}


def test_pipeline_of_awkward_rows(spark, tmp_path):
    """Nulls, empty texts, repeated rows, further columns whose names the stages use themselves, and empty tables."""
    prose = [r["text"] for r in table(spark, SF, "documents").where("lang = 'en' and text is not null").orderBy("doc_id").limit(30).collect()]
    texts = [*AWKWARD, *[(100 + i, t) for i, t in enumerate(prose)], (200, prose[0]), (201, prose[1] + " ")]
    rows = [(i, t, "en" if t in prose else None, "s" if i and i % 2 else None, 0) for i, t in texts]
    clash = {c: F.lit(1) for c in ("n_words", "hits", "items", "sha", "keep_id", "kept", "fp", "fingerprint", "component_id", "owner", "score", "lang_pred", "tokens", "queue", "part")}
    docs = spark.createDataFrame(rows, DOCS).withColumns(clash)
    for name, some in (("some", docs), ("none", docs.limit(0))):
        folder = str(tmp_path / name)
        some.write.parquet(f"{folder}/documents.parquet")
        table(spark, SF, "benchmark").write.parquet(f"{folder}/benchmark.parquet")
        held = table(spark, folder, "documents")
        for _, stage in corpus_pipeline.STAGES[:-1]:
            held = stage(spark, held, folder)
            assert held.columns == docs.columns
        kept = {r["doc_id"] for r in held.collect()}
        packed = corpus_pipeline.run(spark, folder)
        assert {r["doc_id"] for r in packed.collect()} == kept
        if name == "some":
            assert kept and not kept & {1, 2, 3} and not {100, 200} <= kept and not {101, 201} <= kept
        else:
            assert not kept


def test_language_states_without_a_tape_equal_taped_ones_between_the_leads():
    import numpy as np

    from contactscope.llm.language import LEAD, Network

    net, rows = Network(["a", "b"]), np.random.default_rng(3).integers(0, 256, (7, 40 + 2 * LEAD)).astype(np.uint8)
    ahead, back = net._states(rows)
    inner = slice(LEAD, LEAD + 40)
    # both directions in one pass, none over the lead that lies behind it: the states between the leads alone
    assert ahead.shape == back.shape == (40, 7, net.h)
    assert np.allclose(ahead, net._taped("f", rows)[0][inner], atol=1e-5) and np.allclose(back, net._taped("b", rows)[0][inner], atol=1e-5)
    both = np.concatenate((net._taped("f", rows)[0], net._taped("b", rows)[0]), axis=2)[inner]
    for scale in (1, 1000):  # small logits, and those whose exponentials overflow without their maximum taken off
        net.p["V"] *= np.float32(scale)
        logits = (both @ net.p["V"] + net.p["b"]).astype(float)
        want = np.exp(logits - logits.max(axis=2, keepdims=True))
        assert np.allclose(net.label(rows), want / want.sum(axis=2, keepdims=True), atol=1e-3 if scale == 1 else 0.1)
