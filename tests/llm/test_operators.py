"""The ten operators on hard small inputs, against brute force."""

import hashlib
import tempfile
import zlib

import numpy as np
import pytest
from pyspark.sql import functions as F

from signedcluster.llm import (
    bm25_packing,
    boosting,
    chat_format,
    common,
    exact_dedup,
    langid_centroids,
    lsa_decontam,
    quality_weak,
    recurrent_lm,
    simhash_pivots,
    token_binary,
    tokens,
    toxicity_gbt,
)

LONG = " ".join(f"word{k % 977}" for k in range(30_000))
TEXTS = [
    (1, "The cat sat on the mat and looked at the dog."),
    (2, "The cat sat on the mat and looked at the dog."),
    (3, None),
    (4, ""),
    (5, " \n\t "),
    (6, LONG),
    (7, LONG + " tail"),
    (8, "!!! 123"),
    (9, "a"),
    (10, "you are an idiot and a moron, you stupid fool"),
    (10, "you are an idiot and a moron, you stupid fool"),
    (11, "x  y   z <|endoftext|>   é́"),
    (None, "a text without an id"),
    (12, "lower UPPER Été ÄÖ"),
]


@pytest.fixture(scope="module")
def docs(spark):
    rows = [(i, t, "en" if i and i % 2 else None, "s", 5, 7, True) for i, t in TEXTS]
    return spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long, score long, kept boolean")


@pytest.fixture(scope="module")
def none(docs):
    return docs.limit(0)


def test_exact_groups(docs, none):
    for every in (True, False):
        got = exact_dedup.exact_groups(docs, digest_all=every).collect()
        assert len(got) == len(TEXTS)
        by = {}
        for r in got:
            by.setdefault(r["doc_id"], []).append(r)
        assert by[1][0]["keep_id"] == 2 and not by[1][0]["kept"] and by[2][0]["kept"] and by[1][0]["group_size"] == 2
        assert by[3][0]["keep_id"] == by[4][0]["keep_id"] == 4
        assert [r["kept"] for r in by[10]] == [True, True]
        assert by[6][0]["group_size"] == by[7][0]["group_size"] == 1
        assert by[1][0]["text_sha256"] == hashlib.sha256(TEXTS[0][1].encode()).hexdigest()
    assert exact_dedup.exact_groups(none).count() == 0
    kept = exact_dedup.drop_exact_copies(docs)
    assert kept.columns == docs.columns and kept.where("doc_id in (1, 3)").count() == 0 and kept.count() == len(TEXTS) - 2


def brute_fingerprint(text):
    import xxhash

    words = (text or "").encode().lower().split()
    grams = [b" ".join(words[i : i + 4]) for i in range(max(1, len(words) - 3))] if words else []
    h = [xxhash.xxh64_intdigest(g, 42) for g in grams]
    return sum(1 << b for b in range(64) if 2 * sum(x >> b & 1 for x in h) > len(h))


def test_near_duplicates(spark, docs, none):
    got = simhash_pivots.near_duplicates(docs).collect()
    assert len(got) == len(TEXTS)
    want = [(i, brute_fingerprint(t)) for i, t in TEXTS]
    assert sorted((str(r["doc_id"]), r["fp"] % 2**64) for r in got) == sorted((str(i), f) for i, f in want)
    comp = {i: min((j for j, g in want if j is not None and bin(f ^ g).count("1") <= 4), default=None) for i, f in want if i}
    assert {r["doc_id"]: r["component_id"] for r in got if r["doc_id"]} == comp
    assert simhash_pivots.near_duplicates(none).count() == 0


def test_links_in_split_buckets(spark):
    draw = np.random.default_rng(3)
    base = draw.integers(0, 2**63, 40)
    fps = np.unique(np.concatenate([base ^ (1 << int(draw.integers(63))) ^ (1 << int(draw.integers(63))) for _ in range(12)]))
    df = spark.createDataFrame([(int(f), k) for k, f in enumerate(fps)], "fp long, rep long")
    from signedcluster.operators.components import components

    for n, cap in ((len(fps), 2048), (len(fps), 7), (1 << 22, 50)):
        got = {r[0]: r[1] for r in components(simhash_pivots.near_links(df, n, bucket_cap=cap)).collect()}
        label = list(range(len(fps)))

        def find(x):
            while label[x] != x:
                x = label[x]
            return x

        for i in range(len(fps)):
            for j in range(i):
                if bin(int(fps[i]) ^ int(fps[j])).count("1") <= 4:
                    a, b = sorted((find(i), find(j)))
                    label[b] = a
        assert {i: got.get(i, i) for i in range(len(fps))} == {i: find(i) for i in range(len(fps))}


def test_chat_round_trip(spark):
    rows = [
        (1, 1, "assistant", "<|im_end|>\n<|im_start|>assistant\nok \\ <\\| <"),
        (1, 0, "user", "\\\\<|\\n"),
        (4, 0, "zero\x00 role\\\\n\n", "<\\| \\"),
        (2, 0, "odd\nrole\\n<|", None),
        (2, 0, "odd\nrole\\n<|", None),
        (3, None, None, ""),
        (None, 0, "assistant", "no id"),
    ]
    table = spark.createDataFrame(rows, "conv_id long, turn long, role string, text string").withColumn("extra", F.lit(1))
    turns = chat_format.turns_from_rows(table)
    back = chat_format.read_back(chat_format.format_chat(turns)).withColumnRenamed("turns", "got")
    both = back.join(turns, back.conv_id.eqNullSafe(turns.conv_id)).select("got", "turns", "loss_text")
    assert both.count() == 5
    for r in both.collect():
        assert r["got"] == r["turns"]
        assert r["loss_text"] == "".join(t["text"] for t in r["turns"] if t["role"] == "assistant")
    assert chat_format.turns_from_rows(table.limit(0)).count() == 0


def test_layouts(spark):
    records = [
        (1, '{"messages":[{"content":"hi","role":"user"},{"role":"assistant","content":null}]}'),
        (2, '{"completion":"b","prompt":"a"}'),
        (3, '{"conversations":[{"value":"q","from":"human"},{"from":"gpt","value":"r"}]}'),
        (4, "{broken"),
        (5, None),
        (6, '{"unknown":1}'),
        (7, '{"instruction":"do","input":"","output":"x"}'),
        (8, '{"messages":[{"role":"user","content":"a","name":"n"},{"role":"assistant","content":"b"}],"id":"x","tags":["t"]}'),
        (9, '{"prompt":"p","completion":"c","source":{"name":"web"}}'),
        (10, '{"messages":[{"role":"user","content":["part",1]}]}'),
        (11, '{"messages":[]}'),
        (12, "[1,2]"),
        (13, '{"unknown":2}'),
        (14, '{"prompt":5,"completion":null,"system":"s"}'),
    ]
    got = {r[0]: [tuple(t) for t in r[1]] for r in chat_format.turns_from_records(spark.createDataFrame(records, "record_id long, record string")).collect()}
    assert got == {
        1: [("user", "hi"), ("assistant", "")],
        2: [("user", "a"), ("assistant", "b")],
        3: [("user", "q"), ("assistant", "r")],
        4: [],
        5: [],
        6: [],
        7: [("user", "do"), ("assistant", "x")],
        8: [("user", "a"), ("assistant", "b")],
        9: [("user", "p"), ("assistant", "c")],
        10: [("user", '["part",1]')],
        11: [],
        12: [],
        13: [],
        14: [("user", "5"), ("assistant", "")],
    }
    frame = spark.createDataFrame(records, "record_id long, record string")
    found = {r[0]: r for r in chat_format.turns_from_records(frame).collect()}
    assert {k for k, r in found.items() if r["matched"]} == {1, 2, 3, 7, 8, 9, 10, 14} and found[1]["layout"] == found[8]["layout"] == chat_format.MAPPINGS[2].fingerprint
    left = {r["layout"]: r["records"] for r in chat_format.unmatched_layouts(frame).collect()}
    assert left == {None: 3, chat_format.path_fingerprint(["unknown"]): 2, chat_format.path_fingerprint(["messages"]): 1}


def test_schemas_select_mappings(spark):
    rows = spark.createDataFrame([(1, 1, "gpt", "b", 0), (1, 0, "human", "a", 0)], "dialogue_id long, position long, speaker string, utterance string, rows int")
    got = chat_format.turns_from_rows(rows).collect()
    assert [[tuple(t) for t in r["turns"]] for r in got] == [[("user", "a"), ("assistant", "b")]]
    nested = spark.createDataFrame([(4, [("user", "hi", 1), ("assistant", None, 2)]), (5, None)], "conv_id long, messages array<struct<role:string,content:string,score:int>>")
    got = {r["conv_id"]: [tuple(t) for t in r["turns"]] for r in chat_format.turns_from_rows(nested).collect()}
    assert got == {4: [("user", "hi"), ("assistant", "")], 5: []}
    flat = spark.createDataFrame([("q", "a", 1)], "question string, answer string, extra int")
    assert [tuple(t) for t in chat_format.turns_from_rows(flat).first()["turns"]] == [("user", "q"), ("assistant", "a")]
    with pytest.raises(ValueError):
        chat_format.turns_from_rows(flat.select("extra"))


def whole_ids(name, end):
    from tokenizers import Tokenizer

    t = Tokenizer.from_file(tokens.tokenizer_file(name))
    return [(i, [*t.encode(x or "", add_special_tokens=False).ids, end]) for i, x in TEXTS]


def test_token_files(spark, docs, none):
    folder, manifest = token_binary.encode_documents(docs)
    got = sorted(token_binary.read_token_files(spark, folder, manifest).collect(), key=lambda r: r["start"])
    want = whole_ids("word_bpe_49k.json", 2)
    assert [r["doc_id"] for r in got] == sorted((i for i, _ in want), key=lambda i: (i is not None, i))
    assert sorted((str(r["doc_id"]), np.frombuffer(r["ids"], "<u4").tolist()) for r in got) == sorted((str(i), x) for i, x in want)
    at = 0
    for r in got:
        assert r["start"] == at
        at += r["n_tokens"]
    folder, manifest = token_binary.encode_documents(none)
    assert token_binary.read_token_files(spark, folder, manifest).count() == 0
    values = np.array([0, 255, 256, 65535, 65536, 2**24, 2**32 - 1, 7], np.uint32)
    for n in range(len(values) + 1):
        assert (token_binary.unpack_values(*token_binary.pack_values(values[:n]), n) == values[:n]).all()


def test_packing(docs, none):
    got = bm25_packing.pack_documents(docs, window=64).collect()
    ids = {}
    for i, x in whole_ids("byte_bpe_50k.json", 0):
        ids.setdefault(i, x)
    pieces, seqs = {}, {}
    for r in got:
        part = ids[r["doc_id"]][r["start"] : r["start"] + r["length"]]
        assert zlib.crc32(np.array(part, "<u4").tobytes()) == r["ids_crc32"] and len(ids[r["doc_id"]]) == r["doc_tokens"]
        pieces.setdefault(r["doc_id"], []).append((r["start"], r["length"]))
        seqs.setdefault(r["sequence_id"], []).append((r["offset"], r["length"]))
    assert set(pieces) == set(ids)
    for i, x in ids.items():
        copies = sum(j == i for j, _ in TEXTS)
        assert sum(n for _, n in pieces[i]) == copies * len(x)
    for parts in seqs.values():
        at = 0
        for offset, n in sorted(parts):
            assert offset == at
            at += n
        assert at <= 64
    assert sum(sum(n for _, n in p) < 64 for p in seqs.values()) <= 1
    assert bm25_packing.pack_documents(none).count() == 0


def test_packing_prefers_lexical_neighbours():
    terms = [np.array(x) for x in ([1, 2], [3, 4], [1, 2], [3, 4])]
    idf = np.ones(8, np.float32)
    index = bm25_packing.Postings(terms, [np.ones(2)] * 4, np.full(4, 2), idf, 2.0, dense=1.0)
    windows = list(bm25_packing.fill_windows([6, 6, 4, 4], index, 10))
    assert [sorted(k for k, _, _ in w) for w in windows] == [[0, 2], [1, 3]]


def test_language(spark, none):
    en, fr = "the cat sat on the mat with that dog and then they went", "le chat était assis sur le tapis avec les chiens et puis"
    rows = [(k, (en if k % 2 else fr) + f" {k}", "en" if k % 2 else "fr") for k in range(40)] + [(90, None, "en"), (91, "12 !!", "fr"), (92, en, None)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string")
    model = langid_centroids.fit(docs.where("doc_id < 30 or doc_id > 89"), clusters=2)
    got = {r["doc_id"]: r for r in langid_centroids.predict(docs, model).collect()}
    assert all(got[k]["lang_pred"] == ("en" if k % 2 else "fr") for k in range(40))
    assert got[90]["lang_pred"] == got[91]["lang_pred"] == "und" and got[90]["rejected"] and got[92]["lang_pred"] == "en"
    assert langid_centroids.drop_rejected(docs, model).count() == 41
    assert langid_centroids.fit(none) is None
    assert langid_centroids.predict(none, None).count() == 0


def test_language_rejects_unknown_scripts_and_random_letters(spark):
    draw = np.random.default_rng(3)
    stems = {lang: ["".join(draw.choice(list(letters), draw.integers(2, 8))) for _ in range(300)] for lang, letters in {"en": "ethanorsid", "fr": "uqeailéèvm"}.items()}
    made = lambda lang, n: " ".join(draw.choice(stems[lang], n))
    rows = [(k, made(("en", "fr")[k % 2], 10 + k % 60), ("en", "fr")[k % 2]) for k in range(900)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string")
    model = langid_centroids.fit(docs.where("doc_id < 600"), clusters=2)
    odd = [
        "В лесу родилась ёлочка, в лесу она росла, зимой и летом стройная, зелёная была и дожила до праздника",
        "人人生而自由在尊严和权利上一律平等他们赋有理性和良心并应以兄弟关系的精神相对待人人有资格享有本宣言所载的一切权利",
        "Όλοι οι άνθρωποι γεννιούνται ελεύθεροι και ίσοι στην αξιοπρέπεια και τα δικαιώματα και είναι προικισμένοι με λογική",
        *("".join(draw.choice(list("abcdefghijklmnopqrstuvwxyz"), 500)) for _ in range(5)),
    ]
    more = spark.createDataFrame([(10000 + k, t, None) for k, t in enumerate(odd)], docs.schema)
    got = {r["doc_id"]: r["rejected"] for r in langid_centroids.predict(docs.unionByName(more), model).collect()}
    assert all(got[10000 + k] for k in range(len(odd)))
    assert sum(got[k] for k in range(600, 900)) <= 6


def test_boosting_and_calibration():
    draw = np.random.default_rng(1)
    x = draw.random((3000, 4))
    y = ((x[:, 0] > 0.6) ^ (x[:, 1] > 0.5)).astype(float)
    trees = boosting.BoostedTrees(trees=40).fit(x[:2000], y[:2000])
    margin = trees.margin(x[2000:])
    assert ((margin > 0) == (y[2000:] == 1)).mean() > 0.97
    at, value = boosting.isotonic(np.array([1.0, 2, 3, 4]), np.array([0.0, 1, 0, 1]))
    assert value.tolist() == [0.0, 0.5, 0.5, 1.0] and at.tolist() == [1.0, 2.0, 3.0, 4.0]


def test_toxicity(spark, docs, none):
    rows = [(k, f"{'you are a stupid idiot' if k % 4 == 0 else 'you are a good friend'} number {k} " * 3, k % 4 == 0) for k in range(400)]
    many = spark.createDataFrame([(k, t) for k, t, _ in rows], "doc_id long, text string")
    labels = spark.createDataFrame([(k, int(x)) for k, _, x in rows] + [(None, 1), (5, None)], "doc_id long, toxic int")
    got = toxicity_gbt.toxicity(many, labels).where("held_out").collect()
    assert all(r["predicted"] == int(r["doc_id"] % 4 == 0) and 0 <= r["score"] <= 1 for r in got)
    assert toxicity_gbt.toxicity(docs, labels.limit(0)).count() == len(TEXTS)
    assert toxicity_gbt.toxicity(docs, labels.where("doc_id < 12")).count() == len(TEXTS)
    assert toxicity_gbt.toxicity(none, labels).count() == 0


def test_quality(docs, none):
    assert quality_weak.quality(docs).count() == len(TEXTS)
    assert quality_weak.quality(none).count() == 0
    truth = np.random.default_rng(2).random(4000) < 0.7
    acc = np.array([0.9, 0.8, 0.75, 0.6])
    votes = np.where(np.random.default_rng(4).random((4000, 4)) < acc, truth[:, None], ~truth[:, None]).astype(int)
    patterns, counts = np.unique(votes, axis=0, return_counts=True)
    share, table = quality_weak.fit_accuracies(patterns, counts.astype(float))
    assert abs(share - 0.7) < 0.06 and np.abs(table[1, :, 1] - acc).max() < 0.08


def test_language_model(docs, none):
    got = recurrent_lm.score_documents(docs, top_words=50, least_docs=5).collect()
    words = {}
    for i, t in TEXTS:
        words.setdefault(i, (t or "").encode().lower().split())
    held = lambda i: i is None or zlib.crc32(str(i).encode()) % 10 == 0
    seen, n = {}, 0
    for i, t in TEXTS:
        if not held(i):
            n += 1
            for w in (t or "").encode().lower().split():
                seen[w] = seen.get(w, 0) + 1
    total = sum(seen.values()) + n
    z = total + 0.1 * (len(seen) + 2)
    assert len(got) == len(TEXTS)
    for r in got:
        w = words[r["doc_id"]]
        base = sum(np.log10((seen.get(x, 0) + 0.1) / z) for x in w) + np.log10((n + 0.1) / z)
        assert r["n_tokens"] == len(w) + 1 and r["train_tokens"] == total and r["held_out"] == held(r["doc_id"])
        assert r["n_known"] == sum(x in seen for x in w) + 1
        assert abs(r["base_score"] - base) < 1e-6 * abs(base) and r["score"] < 0
    assert recurrent_lm.score_documents(none).count() == 0


def test_recurrent_gradients_and_lanes():
    draw = np.random.default_rng(0)
    unit = recurrent_lm.GatedUnit()
    for k in unit.w:
        unit.w[k] = unit.w[k].astype(np.float64) * 3
    x, y = draw.integers(0, recurrent_lm.CLASSES * recurrent_lm.GROUPS, (2, 4, 3))
    y[0] = recurrent_lm.HEAD + 3 + recurrent_lm.CLASSES * np.arange(3)
    fresh, h = draw.random((4, 3)) < 0.3, draw.standard_normal((3, recurrent_lm.HIDDEN)) * 0.3
    g = unit.window_gradients(x, y, fresh, h)[0]
    for k, w in unit.w.items():
        at = np.unravel_index(np.abs(g[k]).argmax(), g[k].shape)
        w[at] += 1e-3
        up = unit.window_gradients(x, y, fresh, h)[1]
        w[at] -= 2e-3
        down = unit.window_gradients(x, y, fresh, h)[1]
        w[at] += 1e-3
        assert abs(g[k][at] - (up - down) / 2e-3) < 1e-3 * abs(g[k][at]) + 1e-6
    seqs = [draw.integers(0, recurrent_lm.CLASSES * recurrent_lm.GROUPS, n) for n in (1, 90, 40, 3, 64)]
    whole = recurrent_lm.document_log_probs(unit, seqs)
    alone = [recurrent_lm.document_log_probs(unit, [s], window=7)[0] for s in seqs]
    assert np.allclose(whole, alone, rtol=1e-4)


def test_recurrent_training_reads_every_token(monkeypatch):
    draw = np.random.default_rng(1)
    seqs = [draw.integers(0, 50, n) for n in (60_000, 3, 700, *[150] * 90)]
    read, plain = [], recurrent_lm.GatedUnit.window_gradients

    def watched(unit, x, y, fresh, h):
        read.append((y.size, int(fresh.sum())))
        return plain(unit, x, y, fresh, h)

    monkeypatch.setattr(recurrent_lm.GatedUnit, "window_gradients", watched)
    recurrent_lm.train(seqs, epochs=2)
    assert sum(n for n, _ in read) == 2 * sum(map(len, seqs)) and sum(k for _, k in read) == 2 * len(seqs)
    recurrent_lm.train([np.array([recurrent_lm.END])])


def test_decontamination(spark, docs, none):
    draw = np.random.default_rng(5)
    words = [f"w{draw.integers(5000)}x" for _ in range(9000)]
    items = [(k, " ".join(words[40 * k : 40 * k + 36])) for k in range(10)] + [(50, None), (51, ""), (None, "nothing at all")]
    filler = lambda n: " ".join(f"f{draw.integers(3000)}y" for _ in range(n))
    changed = items[3][1].split()
    for k in (2, 7, 12, 17, 22):
        changed[k] = "other"
    rows = [(1000, f"{filler(50)} {items[0][1].upper()} {filler(70)}"), (1001, filler(300)), (1002, f"{filler(9)} {' '.join(changed)}")]
    table = spark.createDataFrame(rows, "doc_id long, text string").unionByName(docs.select("doc_id", "text"))
    bench = spark.createDataFrame(items, "item_id long, text string")
    got = {(r["doc_id"], r["item_id"]) for r in lsa_decontam.contaminated_pairs(table, bench).collect()}
    assert got == {(1000, 0), (1002, 3)}
    assert lsa_decontam.contaminated_pairs(none, bench).count() == 0
    assert lsa_decontam.contaminated_pairs(table, bench.limit(0)).count() == 0
    kept = lsa_decontam.drop_contaminated(table, bench)
    assert kept.count() == table.count() - 2
    a, b = list("abcbdab".encode()), list("bdcaba".encode())
    assert lsa_decontam.longest_common_subsequence(a, b) == 4


def test_pipeline_stages(spark):
    import corpus_pipeline

    folder = "/root/testdata/sf0.001"
    docs = spark.read.parquet(f"{folder}/documents.parquet")
    columns = docs.columns
    for name, stage in corpus_pipeline.STAGES[:-1]:
        left = stage(spark, docs, folder)
        assert left.columns == columns
        from signedcluster.shared import materialize

        kept = materialize(left, name)
        ids = {r[0] for r in kept.select("doc_id").collect()}
        if name == "exact_dedup":
            want = {}
            for r in docs.collect():
                want[r["text"]] = max(want.get(r["text"], -1), r["doc_id"])
            assert ids == set(want.values())
        docs = kept
    packed = corpus_pipeline.STAGES[-1][1](spark, docs, folder)
    assert {r[0] for r in packed.select("doc_id").collect()} == {r[0] for r in docs.select("doc_id").collect()}


#: Spaces, signs and separators at which a cut between words could go wrong.
AWKWARD = [
    None, "", " ", "a", "a ", " a", "  ", "a  b", "a\n b", "a \nb", "x　y", "<|endoftext|> b", "\x1c a", "É b É", "a\tb  c\n",
    "..a b..", "日本 語", "İ x", "á b́", "don't. 's 'S", "a.b. a!. é. a. b, .", "a.", "a.\n b", "1. a:. b;", ".", "x. ",
    "I'S. 's. '. a'", "ﬁ ﬁ.", "a.\nB c", "a\n\nb", "\na", "a\n", "a \nb", "a\n b", "x　\n　y", "\x01 a", "a &&& b*** c...",
    "É. ß, ü!? ×. ÷, ſ. İ. J̌ ǰ İ", "Straße, Ñandú; ÇA!", "a#######. b!!!! c", "ǅx ǅ ŉ", "don't! 'S. L'été.", " a\nb ",
]


def test_words_by_arrow_give_the_ids_of_whole_texts():
    import pyarrow as pa

    from signedcluster.llm import tokens

    for name, keep_space in (("byte_bpe_50k.json", True), ("word_bpe_49k.json", False)):
        path = tokens.tokenizer_file(name)
        coder = tokens.ChunkEncoder(path, keep_space, tokens.id_type(path))
        texts = [*AWKWARD, " ".join(t for t in AWKWARD if t and "<|" not in t)]
        for some in (texts, texts[:1], texts[::-1], [t for t in texts for _ in range(2)], []):
            got = coder.encode_all(pa.array(some, pa.string()))
            for text, ids in zip(some, got.to_pylist(), strict=True):
                assert ids == coder.whole(text or "")


def test_decontamination_finds_each_of_many_passages(spark):
    draw = np.random.default_rng(9)
    words = [f"w{int(20000 * draw.random() ** 2)}x" for _ in range(60000)]
    items = [(k, " ".join(words[20 * k : 20 * k + 20])) for k in range(2500)]
    rows = [(k, " ".join([*words[50000 + 40 * k : 50020 + 40 * k], items[11 * k][1], *words[50020 + 40 * k : 50040 + 40 * k]])) for k in range(220)]
    docs, bench = spark.createDataFrame(rows, "doc_id long, text string"), spark.createDataFrame(items, "item_id long, text string")
    got = {(r["doc_id"], r["item_id"]) for r in lsa_decontam.contaminated_pairs(docs, bench).collect()}
    assert {(k, 11 * k) for k in range(220)} <= got
    df, n = lsa_decontam.document_frequencies(docs)
    index = lsa_decontam.Index(spark, items, df, n, 96)
    assert len(index.latent) > 20 and index.kept.min() > 0.999
    import pyarrow as pa

    texts = pa.array([*(t for _, t in rows[:40]), None, "", "one", *(t for _, t in rows[40:50])])
    words, at, edges = common.numbered_words(texts)
    assert [words[int(k)].as_py() for k in at] == [w.decode() for t in texts.to_pylist() for w in common.words_of(t)]
    blocks = lsa_decontam.blocks_of(lsa_decontam.slots_of(words)[at], edges, index.idf)
    whole = lsa_decontam.candidates_within(blocks, 0, len(blocks.doc), index, 0.25)
    parts = lsa_decontam.find_candidates(blocks, index, 0.25)
    assert len(whole[0]) and {x[:3] for x in zip(*map(np.ndarray.tolist, whole), strict=True)} == {x[:3] for x in zip(*map(np.ndarray.tolist, parts), strict=True)}
    # Brute force: the TF-IDF cosine of every window of every text with every passage, blocks counting words once.
    of = lambda t: [lsa_decontam.slots_of(pa.array(b))  for b in (t[k : k + 16] for k in range(0, len(t), 16))]
    want = set()
    passages = [(np.unique(lsa_decontam.slots_of(pa.array([w.decode() for w in p])), return_counts=True)) for p in index.words]
    matrix = np.zeros((len(passages), lsa_decontam.SLOTS), np.float32)
    for k, (held, tf) in enumerate(passages):
        matrix[k, held] = index.idf[held] * tf
    matrix /= np.linalg.norm(matrix, axis=1, keepdims=True)
    first = 0
    for t in texts.to_pylist():
        pieces = [np.unique(x) for x in of([w.decode() for w in common.words_of(t)])]
        for width in (2, 4):
            for a in range(max(len(pieces) - width + 1, min(len(pieces), 1))):
                held = np.concatenate(pieces[a : a + width])
                size = np.sqrt((index.idf[held].astype(float) ** 2).sum())
                want |= {(first + a, width, int(p)) for p in np.flatnonzero(np.add.reduce(matrix[:, held] * index.idf[held], 1) / size >= 0.25)}
        first += len(pieces)
    got = {x[:3] for x in zip(*map(np.ndarray.tolist, parts), strict=True)}
    assert len(got ^ want) <= 0.01 * len(want)


def test_slots_do_not_depend_on_their_neighbours():
    import pyarrow as pa

    words = ["a", "", "(word)", "word", "...", "é!", "é", "x" * 5000, "Wort,", "Wort", "a"]
    got = lsa_decontam.slots_of(pa.array(words))
    alone = [int(lsa_decontam.slots_of(pa.array([w]))[0]) for w in words]
    assert got.tolist() == alone and got[2] == got[3] and got[5] == got[6] and got[8] == got[9] and got[0] == got[10]
    assert len(set(alone)) == 6 and lsa_decontam.slots_of(pa.array([], pa.string())).tolist() == []
    many = pa.array([f"w{k}" for k in range(200_000)])
    assert len(np.unique(lsa_decontam.slots_of(many))) > 0.95 * lsa_decontam.SLOTS * (1 - np.exp(-200_000 / lsa_decontam.SLOTS))


def test_pipeline_drops_judge_rows_not_ids(spark):
    """Repeated and null ids, a clashing column: one row's verdict must not touch another row of its id."""
    en = "the quick brown fox jumps over the lazy dog near the old river bank while seven wise owls watch from tall trees"
    leak = " ".join(f"leak{k}word" for k in range(40))
    schema = "doc_id long, text string, lang string, gone_id long, mark long, _gone_id long"
    make = lambda rows: spark.createDataFrame([(i, t, "en", 1, 2, 3) for i, t in rows], schema)
    left = lambda df: sorted(((r["doc_id"], r["text"]) for r in df.collect()), key=str)
    rows = [(5, "copy me"), (5, "unique " + en), (7, "copy me"), (None, "copy me"), (None, None), (3, ""), (None, "alone")]
    got = exact_dedup.drop_exact_copies(make(rows))
    assert got.columns == [f.split()[0] for f in schema.split(", ")]
    assert left(got) == sorted([(5, "unique " + en), (7, "copy me"), (3, ""), (None, "alone")], key=str)
    near = [(1, en + " one"), (4, en + " one"), (4, "something else entirely, of other words and another length"), (None, en + " one"), (None, "lonely text of null id")]
    got = simhash_pivots.keep_one_per_class(make(near))
    assert left(got) == sorted([(1, en + " one"), near[2], near[4]], key=str)
    leaks = [(1, f"{en} {leak}"), (1, en), (None, f"{leak} {en}"), (None, en), (2, None)]
    bench = spark.createDataFrame([(9, leak), (None, None)], "item_id long, text string")
    assert left(lsa_decontam.drop_contaminated(make(leaks), bench)) == sorted([(1, en), (None, en), (2, None)], key=str)
    model = langid_centroids.fit(make([(k, f"{en} {k}") for k in range(60)]), clusters=2)
    odd = [(1, en), (1, "12 !!"), (None, "³ ½"), (None, en), (2, None)]
    assert left(langid_centroids.drop_rejected(make(odd), model)) == sorted([(1, en), (None, en)], key=str)


def test_full_digests_are_read_for_survivors_only(spark):
    """Lengths, then prefixes, then digests: rows that differ before the full hash never come to it."""
    rows = [(k, "x" * k) for k in range(1, 200)] + [(1000 + k, f"{k:05d}" + "y" * 300) for k in range(300)] + [(k, "same start " * 10 + f"{k:05d}") for k in range(5000, 5040)] + [(9000, "x"), (9001, "z" * 70)]
    frame = spark.createDataFrame(rows, "doc_id long, text string")
    left = {tuple(r) for r in exact_dedup.refined(frame, 64).select("bytes").collect()}
    assert left == {(1,), (115,)}
    found = exact_dedup.digests(frame, "doc_id", "text", 64, False)
    level3 = {r[0] for r in found.where("digest is not null").select("doc_id").collect()}
    assert {1, 9000, *range(5000, 5040)} <= level3 and len(level3) < 60
    got = {r["doc_id"]: r for r in exact_dedup.exact_groups(frame, digest_all=True).collect()}
    assert all((r["group_size"], r["keep_id"]) == ((2, 9000) if i in (1, 9000) else (1, i)) for i, r in got.items())
    assert all(r["text_sha256"] == hashlib.sha256(dict(rows)[i].encode()).hexdigest() for i, r in got.items())


def test_without_rows_by_filter(spark, monkeypatch):
    """Beyond the broadcast bound the bit filter and a join give the same rows."""
    docs = spark.range(5000).select((F.col("id") % 2500).alias("doc_id"), F.when(F.col("id") % 7 > 0, F.concat(F.lit("t"), "id")).alias("text"), F.lit(1).alias("_among_gone"))
    docs = docs.unionByName(spark.createDataFrame([(None, "n", 1), (None, None, 1)], docs.schema))
    gone = docs.where("doc_id % 3 = 0 and doc_id < 2400 or doc_id is null and text = 'n'").where("text is null or text < 't4'").select("doc_id", common.text_mark())
    want = sorted(map(str, common.without_rows(docs, gone).collect()))
    monkeypatch.setattr(common, "few", lambda frame, rows=0: frame)
    monkeypatch.setattr(common, "FILTER_BITS", 1 << 15)
    assert sorted(map(str, common.without_rows(docs, gone).collect())) == want and 0 < len(want) < 5002
    assert common.without_rows(docs, gone).columns == docs.columns


def test_scores_are_bm25_over_all_terms():
    draw = np.random.default_rng(8)
    docs = [np.minimum(draw.zipf(1.3, draw.integers(1, 400)), 300) - 1 for _ in range(60)]
    docs[5] = np.full(700, 3)
    terms, counts = zip(*(np.unique(d, return_counts=True) for d in docs), strict=True)
    df = np.bincount(np.concatenate(terms), minlength=300)
    idf = np.log1p((60 - df + 0.5) / (df + 0.5)).astype(np.float32)
    lengths = np.array([len(d) for d in docs])
    for dense in (0.0, 0.05, 0.5, 1.0):
        index = bm25_packing.Postings(list(terms), list(counts), lengths, idf, lengths.mean(), dense)
        for seed in (0, 5, 33):
            want = []
            for t, c, n in zip(terms, counts, lengths, strict=True):
                tf = dict(zip(t.tolist(), c.tolist(), strict=True))
                want.append(sum(idf[x] * tf[x] * 2.2 / (tf[x] + 1.2 * (0.25 + 0.75 * n / lengths.mean())) for x in terms[seed].tolist() if x in tf))
            assert np.allclose(index.scores(seed), want, rtol=1e-3, atol=1e-3)


def test_shards_are_bounded_and_keep_routes_together():
    df = np.arange(100) + 1
    plan = bm25_packing.plan_shards([(-1, 5), (3, 40), (4, 70), (7, 1000), (9, 30), (12, 60)], df, 100)
    assert plan == [(-1, 0, 1), (3, 0, 1), (4, 1, 1), (7, 2, 10), (9, 12, 1), (12, 12, 1)]
    assert bm25_packing.route_of(np.array([5, 9, 2]), np.array([0, 0, 4, 0, 0, 1, 0, 0, 0, 2])) == 9
    assert bm25_packing.route_of(np.array([5]), np.array([0, 0, 4, 0, 0, 1])) == -1


def test_language_model_is_a_distribution_and_learns(spark):
    """Probabilities of all possible next words (one unseen word a group) sum to one; order in the words is learned."""
    draw = np.random.default_rng(4)
    halves = [[f"{a}{k}x{a}" for k in range(120)] for a in ("ab", "cd")]
    rows = [(k, " ".join(draw.choice(halves[k % 2], 60))) for k in range(600)]
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    got = recurrent_lm.score_documents(docs, top_words=100, least_docs=300, rounds=3).collect()
    held = [r for r in got if r["held_out"]]
    assert len(held) > 30 and sum(r["score"] - r["base_score"] for r in held) / sum(r["n_tokens"] for r in held) > 0.2
    unit = recurrent_lm.GatedUnit()
    state = draw.standard_normal((1, recurrent_lm.HIDDEN)).astype(np.float32)
    unit.w["group"][:] = draw.standard_normal(unit.w["group"].shape)
    codes = [c for c in range(recurrent_lm.HEAD)] + [recurrent_lm.END] + [c + recurrent_lm.CLASSES * g for c in range(recurrent_lm.HEAD, recurrent_lm.END) for g in range(recurrent_lm.GROUPS)]
    states, target = np.repeat(state, len(codes), 0), np.array(codes)
    total = np.exp(unit.class_log_probs(states, target % recurrent_lm.CLASSES) + unit.group_log_probs(states, target)).sum()
    assert abs(total - 1) < 1e-4


def test_every_training_text_teaches_the_recurrent_weights(spark, tmp_path, monkeypatch):
    """Texts have lengths of their own, so the lengths that training tasks see tell which texts they read."""
    docs = spark.createDataFrame([(k, "a " * k) for k in range(400)], "doc_id long, text string")
    folder = str(tmp_path)

    def watched(unit, seqs, done, share, **more):
        with tempfile.NamedTemporaryFile("w", dir=folder, suffix=f"-{done:.3f}", delete=False) as out:
            out.write(" ".join(str(len(s) - 1) for s in seqs))

    monkeypatch.setattr(recurrent_lm, "epoch", watched)
    learn = [k for k in range(400) if zlib.crc32(str(k).encode()) % 10]
    read = lambda: sorted(int(n) for f in tmp_path.iterdir() for n in f.read_text().split())
    recurrent_lm.score_documents(docs, least_docs=20)
    assert sorted(set(read())) == learn and len(read()) <= len(learn) + 3
    for f in tmp_path.iterdir():
        f.write_text("")
    recurrent_lm.score_documents(docs, least_docs=1000)
    assert read() == sorted(learn * 3)


def test_scores_do_not_depend_on_texts_of_the_same_lane():
    draw = np.random.default_rng(6)
    unit = recurrent_lm.GatedUnit()
    unit.w["out"] *= 20
    seqs = [np.append(draw.integers(0, recurrent_lm.HEAD, n), recurrent_lm.END) for n in (3, 30, 8, 0, 12, 5, 21)]
    alone = [recurrent_lm.document_log_probs(unit, [s])[0] for s in seqs]
    assert np.allclose(recurrent_lm.document_log_probs(unit, seqs, lanes=2), alone, rtol=1e-5)


def test_a_token_of_the_language_model_takes_few_exponentials(monkeypatch):
    """64 gates, 32 new values, 8 spans, 16 classes of a span, 32 groups of a class: not an exponential for each class."""
    draw, taken, plain = np.random.default_rng(7), [], np.exp

    def counted(x, *more, **named):
        taken.append(np.size(x))
        return plain(x, *more, **named)

    monkeypatch.setattr(np, "exp", counted)
    unit = recurrent_lm.GatedUnit()
    codes = draw.integers(0, recurrent_lm.CLASSES * recurrent_lm.GROUPS, 2000)
    recurrent_lm.document_log_probs(unit, [codes])
    assert sum(taken) <= 2000 * (3 * recurrent_lm.HIDDEN + 24 + recurrent_lm.GROUPS)
    taken.clear()
    recurrent_lm.train([codes], epochs=1, unit=unit)
    assert sum(taken) <= 2000 * (3 * recurrent_lm.HIDDEN + 24 + recurrent_lm.GROUPS)


def test_bounds_of_logits_do_not_change_the_language_model():
    """Logits of any size, of each factor: probabilities stay finite and sum to one over all classes and groups."""
    draw, unit = np.random.default_rng(8), recurrent_lm.GatedUnit()
    for k in ("span", "out", "group"):
        unit.w[k] = (draw.standard_normal(unit.w[k].shape) * 200).astype(np.float32)
    codes = [c for c in range(recurrent_lm.HEAD)] + [recurrent_lm.END] + [c + recurrent_lm.CLASSES * g for c in range(recurrent_lm.HEAD, recurrent_lm.END) for g in range(recurrent_lm.GROUPS)]
    state = draw.standard_normal((1, recurrent_lm.HIDDEN)).astype(np.float32)
    got = unit.log_probs(np.repeat(state, len(codes), 0), np.array(codes), unit.ready())
    assert np.isfinite(got).all() and abs(np.exp(got).sum() - 1) < 1e-4
