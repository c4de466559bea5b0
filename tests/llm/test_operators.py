"""The pipeline's operators against brute force, and their edge cases."""

from __future__ import annotations

import collections
import hashlib
import re
import zlib

import numpy as np
import pytest
import xxhash
from pyspark.sql import functions as F

from steerselect.llm import exact_dedup, packing, pii, piece_codec, sharding, similar, simhash, superkmer, topk_search, toxicity, warc
from steerselect.llm.queries import vocabulary

SCHEMA = "doc_id long, text string, kept boolean, id string"
WORDS = "alpha beta gamma delta eps zeta eta theta iota kappa".split()


def text_of(seed: int, n: int) -> str:
    r = np.random.default_rng(seed)
    return " ".join(f"{WORDS[i]}{j}" for i, j in zip(r.integers(0, 10, n), r.integers(0, 50, n)))


@pytest.fixture(scope="module")
def odd(spark):
    long = text_of(1, 4000)
    near = long.replace("alpha1 ", "other ", 1)
    rows = [(1, long), (2, long), (3, near), (4, None), (5, ""), (6, " \t\n"), (7, "Hello  World"), (8, "hello world"), (9, text_of(2, 60) + "  " + text_of(3, 40)), (10, "x " + text_of(3, 40)), (11, "a b a b " * 40), (None, "no id"), (7, "Hello  World")]
    return spark.createDataFrame([(i, t, True, "x") for i, t in rows], SCHEMA)


@pytest.fixture(scope="module")
def empty(spark):
    return spark.createDataFrame([], SCHEMA)


def test_exact_dedup(odd, empty):
    got = exact_dedup.exact_dedup(odd, share=2).collect()
    groups = collections.defaultdict(list)
    for r in odd.collect():
        groups[re.sub(r"[\x20\x09-\x0D]", "", r.text or "")].append(r)
    assert len(got) == 13 and sum(r.kept for r in got) == len(groups)
    for t, members in groups.items():
        sha = hashlib.sha256(t.encode()).hexdigest()
        mine = [r for r in got if r.text_sha256 == sha]
        best = min(members, key=lambda r: (-len(r.text or ""), r.doc_id is None, r.doc_id or 0))
        assert {r.keep_id for r in mine} == {best.doc_id} and {r.group_size for r in mine} == {len(members)}
    assert exact_dedup.drop_copies(odd, share=2).count() == len(groups)
    assert exact_dedup.exact_dedup(empty).count() == 0 and exact_dedup.drop_copies(empty).count() == 0


@pytest.mark.parametrize("hot", [16384, 2])
def test_simhash(spark, odd, empty, hot):
    got = simhash.near_duplicates(odd, hot=hot).collect()
    assert len(got) == 13
    fps = sorted({int(r.fingerprint, 16) for r in got})
    comp = {f: f for f in fps}
    for _ in fps:
        for a in fps:
            for b in fps:
                if (a ^ b).bit_count() <= 2:
                    comp[a] = comp[b] = min(comp[a], comp[b])
    low = {}
    for r in got:
        c = comp[int(r.fingerprint, 16)]
        if r.doc_id is not None:
            low[c] = min(low.get(c, 1 << 60), r.doc_id)
    assert all(r.component_id == low.get(comp[int(r.fingerprint, 16)]) for r in got)
    assert {r.fingerprint for r in got if r.doc_id in (4, 5, 6)} == {"0" * 16}
    w = text_of(2, 9).split()
    n = [0] * 64
    for i in range(7):
        h = xxhash.xxh64_intdigest(" ".join(w[i : i + 3]).encode(), 42)
        n = [c + (h >> k & 1) for k, c in enumerate(n)]
    assert simhash.fingerprint(" ".join(w).upper()) == sum(1 << k for k, c in enumerate(n) if 2 * c > 7)
    assert simhash.near_duplicates(empty).count() == 0 and simhash.keep_one(empty).count() == 0


def test_near_copies_go_and_others_stay(spark):
    base = text_of(9, 300)
    rows = [(1, base), (2, base.replace(" ", " new ", 2)), (3, text_of(10, 300)), (4, text_of(11, 20))]
    df = spark.createDataFrame(rows, "doc_id long, text string")
    assert sorted(r.doc_id for r in simhash.keep_one(df).collect()) == [1, 3, 4]


@pytest.mark.parametrize("dense", [2048, 2])
def test_near_copies_against_all_pairs(spark, dense):
    """Groups whose members lie around the similarity bound, with spanning forests and without."""
    r = np.random.default_rng(7)
    docs = [(0, None), (1, ""), (2, " "), (3, "A b"), (4, "a B")]
    for g in range(4):
        base = text_of(100 + g, 90).split()
        for k in range(12):
            w = list(base)
            for at in r.integers(0, len(w), k // 3 + (g > 1)):
                w[at] = f"new{g}x{k}"
            docs.append((len(docs), " ".join(w)))
    df = spark.createDataFrame(docs, "doc_id long, text string").repartition(3)
    sets = {i: set() for i, _ in docs}
    prints = {i: simhash.fingerprint(t) for i, t in docs}
    for i, t in docs:
        w = (t or "").lower().split()
        sets[i] = {" ".join(w[k : k + 5]) for k in range(max(1, len(w) - 4))} if w else set()
    near = [(a, b) for a in sets for b in sets if a < b and (prints[a] ^ prints[b]).bit_count() <= 11 and 10 * len(sets[a] & sets[b]) >= 8 * len(sets[a] | sets[b])]
    root = {i: i for i in sets}
    for _ in sets:
        for a, b in near:
            root[a] = root[b] = min(root[a], root[b])
    got = {x.node: x.root for x in simhash.verified_groups(df, dense=dense).collect()}
    assert {i: got.get(i, i) for i in sets} == root and len(set(root.values())) > 10
    assert sorted(x.doc_id for x in simhash.keep_one(df, dense=dense).collect()) == sorted(set(root.values()))


@pytest.mark.parametrize("dense", [16, 1])
def test_near_copies_at_any_distance_of_fingerprints(spark, dense):
    """The reference is the similarity alone; some of its pairs have fingerprints more than 11 bits apart."""
    r = np.random.default_rng(3)
    docs = [(0, None), (1, ""), (2, "one line of text that all have")]
    for g in range(40):
        base = text_of(500 + g, 150).split()
        for k in range(3):
            w, at = list(base), int(r.integers(0, 130))
            w[at : at + 5 * k] = [f"new{g}x{k}y{i}" for i in range(5 * k)]
            docs.append((len(docs), " ".join(w)))
    sets = {i: {" ".join(w[k : k + 5]) for k in range(max(1, len(w) - 4))} if (w := (t or "").lower().split()) else set() for i, t in docs}
    alike = [(a, b) for a in sets for b in sets if a < b and 10 * len(sets[a] & sets[b]) >= 8 * len(sets[a] | sets[b])]
    prints = {i: simhash.fingerprint(t) for i, t in docs}
    assert any((prints[a] ^ prints[b]).bit_count() > 11 for a, b in alike)
    root = {i: i for i in sets}
    for _ in range(5):
        for a, b in alike:
            root[a] = root[b] = min(root[a], root[b])
    got = {x.node: x.root for x in similar.similar_groups(spark.createDataFrame(docs, "doc_id long, text string"), dense=dense).collect()}
    assert {i: got.get(i, i) for i in sets} == root


def test_the_pipeline_finds_copies_with_distant_fingerprints(spark):
    import corpus_pipeline

    base = text_of(43, 300).split()
    for at in range(0, 260, 2):
        copy = base[:at] + [f"other{i}" for i in range(26)] + base[at + 26 :]
        if (simhash.fingerprint(" ".join(base)) ^ simhash.fingerprint(" ".join(copy))).bit_count() > 11:
            break
    else:
        raise AssertionError("no distant copy")
    df = spark.createDataFrame([(1, " ".join(base)), (2, " ".join(copy)), (3, text_of(44, 300))], "doc_id long, text string")
    assert sorted(r.doc_id for r in corpus_pipeline.different(spark, df, "").collect()) == [1, 3]


def test_classes_hold_every_document(spark, tmp_path):
    from steerselect.llm import queries

    base = text_of(1, 200)
    texts = [base, base + " tail", text_of(2, 200), "too short", "Too, short!", "alone", base[: len(base) // 2] + " " + text_of(3, 100)]
    spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string").write.parquet(f"{tmp_path}/documents.parquet")
    got = {r.doc_id: r.class_id for r in queries.queries()["near_dup_classes"](spark, str(tmp_path)).collect()}
    words = [[w for w in re.split(r"[^a-z]+", t.lower()) if w] for t in texts]
    sets = [{" ".join(w[k : k + 5]) for k in range(max(1, len(w) - 4))} for w in words]
    root = list(range(len(texts)))
    for _ in root:
        for a, x in enumerate(sets):
            for b, y in enumerate(sets):
                if 10 * len(x & y) >= 8 * len(x | y):
                    root[a] = root[b] = min(root[a], root[b])
    assert got == dict(enumerate(root)) and got[1] == 0 and got[4] == 3 and got[5] == 5


def test_dense_tiles_keep_components():
    r = np.random.default_rng(0)
    a = np.unique(np.array([int(f) ^ (1 << int(i)) ^ (1 << int(j)) for f in [0, 2**63 + 12345] for i, j in r.integers(0, 64, (2500, 2))], np.uint64))
    a = a[np.argsort(np.bitwise_count(a), kind="stable")]
    u, v = simhash.tile_links(a, a, 2, True)
    assert len(u) < 3 * len(a) and (np.bitwise_count(a[u] ^ a[v]) <= 2).all()
    label = np.arange(len(a))
    while True:
        new = label.copy()
        np.minimum.at(new, u, label[v])
        np.minimum.at(new, v, label[u])
        if (new == label).all():
            break
        label = new
    assert len(set(label.tolist())) == 2


@pytest.mark.parametrize("how", [{}, {"hot_share": 0, "hot_least": 1}])
def test_substrings(odd, empty, how):
    docs = [(r.doc_id, re.findall(r"[^\x20\x09-\x0D]+", r.text or "")) for r in odd.collect()]
    seen = collections.Counter(tuple(w[k : k + 35]) for _, w in docs for k in range(len(w) - 34))
    want = []
    for i, w in docs:
        gone = {p for k in range(len(w) - 34) if seen[tuple(w[k : k + 35])] > 1 for p in range(k, k + 35)}
        want.append((i, len(w), len(gone), " ".join(x for p, x in enumerate(w) if p not in gone)))
    got = [tuple(r) for r in superkmer.remove_repeats(odd, **how).collect()]
    assert sorted(got, key=str) == sorted(want, key=str)
    assert superkmer.remove_repeats(empty).count() == 0


def test_top_k(spark):
    r = np.random.default_rng(3)
    x = r.normal(size=(700, 24))
    x[5], x[6] = x[0], x[0]
    rows = [(i, v.tolist()) for i, v in enumerate(x)] + [(1000, None), (1001, [float("nan")] * 24), (1002, [1.0, None]), (None, [1.0] * 24), (1100, [0.5])]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<double>")
    got = collections.defaultdict(list)
    for q in topk_search.exact_top_k(df, F.col("vec_id") % 100 == 0).orderBy("query_id", "rank").collect():
        got[q.query_id].append((q.vec_id, q.score))
    ids = [*range(700), 1100]
    ints = np.floor(1024 * np.vstack((x, [[0.5] + [0] * 23]))).astype(np.int64)
    assert sorted(got) == [0, 100, 200, 300, 400, 500, 600, 1100]
    for q in got:
        s = ints @ ints[ids.index(q)]
        assert got[q] == [(i, v) for v, i in sorted(((-int(v), i) for v, i in zip(s, ids) if i != q))[:10] for v in [-v]]
    assert topk_search.exact_top_k(df.limit(0), F.lit(True)).count() == 0


def test_top_k_takes_rows_of_repeated_ids(spark):
    r = np.random.default_rng(8)
    x = r.integers(-3, 4, (60, 5)).astype(float)
    x[1], x[2] = x[0], -x[0]
    ids = [100, 100, 100, *(int(i) for i in r.integers(0, 30, 57) * 10)]
    df = spark.createDataFrame([(i, v.tolist(), "z", 1.0) for i, v in zip(ids, x)], "vec_id long, embedding array<double>, id string, score double")
    got = collections.Counter((q.query_id, q["rank"], q.vec_id, q.score) for q in topk_search.exact_top_k(df, F.col("vec_id") % 100 == 0, k=4).collect())
    want = collections.Counter()
    ints = (1024 * x).astype(np.int64)
    for n, i in enumerate(ids):
        if i % 100 == 0:
            s = ints @ ints[n]
            for k, (v, j) in enumerate(sorted((-int(s[m]), ids[m]) for m in range(60) if m != n)[:4]):
                want[(i, k + 1, j, -v)] += 1
    assert got == want


def test_a_reader_task_for_each_archive(spark):
    df = spark.createDataFrame([(f"/nowhere/{i}", 1, 1) for i in range(40)], "path string, captures long, bytes long")
    assert warc.read_archives(df, "file:///nowhere").rdd.getNumPartitions() == 40


def test_words_of_any_letters_are_packed_right():
    import pyarrow as pa
    from tokenizers import Tokenizer

    r, file = np.random.default_rng(1), vocabulary("word_bpe_49k.json")
    tok, enc = Tokenizer.from_file(file), packing.WordEncoder(file)
    parts = [*"abcIJKéÉßÇİıŸſµª²¼019 .,;:!?'-_&%$\n\t\r\x1c\x85\xa0\xad\x01Ωдあ", "'s", "'T", "İ!", "İ.", "<|endoftext|>", "can't."]
    texts = ["".join(r.choice(parts, r.integers(0, 50))) for _ in range(1500)] + ["ÇİÇEKLİ.", "", "a" * 3000]
    for t, ids in zip(texts, enc.encode_all(pa.array(texts))):
        assert ids.tolist() == tok.encode(t, add_special_tokens=False).ids


def test_prefix_tables_agree_with_the_library():
    import sentencepiece

    file = vocabulary("piece_bpe_32k.model")
    lib, c, r = sentencepiece.SentencePieceProcessor(model_file=file), piece_codec.PieceCodec(file), np.random.default_rng(2)
    parts = [*"abcdeéıİ▁ \n\t\r019.,;'-&$\x00\xa0日€𝄞д", "  ", " \n", "\n ", "<s>", "<0x0A>", "the ", "tion"]
    for t in ["".join(r.choice(parts, r.integers(0, 50))) for _ in range(1500)]:
        ids = lib.encode(t, add_bos=True, add_eos=True)
        assert c.encode(t) == ids and c.decode_bytes(np.array(ids)).decode() == lib.decode(ids)
    some = r.choice(sorted(c.halves), (1500, 2))
    assert all(c._fits(c.plain[a] << 20 | c.plain[b]) == (c.merged(a + b) == [a, b]) for a, b in some.tolist())


@pytest.mark.parametrize("how", [{}, {"tile": 4}, {"tile_hashes": 300}])
def test_regions_of_several_tiles_lose_no_link(spark, how):
    r = np.random.default_rng(11)
    docs = []
    for g in range(3):
        base = text_of(900 + g, 80).split()
        for k in range(14):
            w = list(base)
            for at in r.integers(0, len(w), k // 4 + g):
                w[at] = f"n{g}x{k}"
            docs.append((len(docs), " ".join(w)))
    sets = {i: {" ".join(w[k : k + 5]) for k in range(len(w) - 4)} for i, t in docs for w in [t.split()]}
    root = {i: i for i in sets}
    for _ in sets:
        for a in sets:
            for b in sets:
                if 10 * len(sets[a] & sets[b]) >= 8 * len(sets[a] | sets[b]):
                    root[a] = root[b] = min(root[a], root[b])
    got = {x.node: x.root for x in similar.similar_groups(spark.createDataFrame(docs, "doc_id long, text string"), **how).collect()}
    assert {i: got.get(i, i) for i in sets} == root


def test_surrogates(spark, odd, empty):
    t = 'mail Ann.42@Mail3.example.com or ann.42@mail3.example.com, "+1 (275) 555-5927", 8.20.209.178; card 4539 1488 0343 6467, not 1234567890123456; token = "9233A8ECF7C5B09FE5949719B6B82BC439E9329B" Frau Anna Schmidt, Herr Schmidt'
    new, log = pii.replaced(t, b"key", {})
    kinds = [k for k, _, _ in log]
    assert kinds == ["email", "email", "phone", "ip", "card", "secret", "person", "person"]
    assert log[0][2].lower() == log[1][2].lower() and log[1][2].endswith(".com") and "1234567890123456" in new
    assert pii.luhn(re.sub(r"\D", "", log[4][2])) and log[4][2][4] == " " and re.fullmatch("[0-9A-F]{40}", log[5][2])
    assert log[6][2].split()[1] == log[7][2] and log[6][2].split()[0] in pii.GIVEN["latin", "f"]
    assert not any(found in new for _, found, _ in log)
    assert pii.replaced("clean text, 1984 and 3.14", b"key", {})[0] == "clean text, 1984 and 3.14"
    kept = {(r.doc_id, r.text) for r in odd.collect()}
    assert {(r.doc_id, r.text) for r in pii.replace_entities(odd).collect()} == kept
    assert pii.replace_entities(empty).count() == 0


def test_names_keep_their_bearers(spark):
    """Distinct people stay distinct, and a family name has one surrogate, whatever collides."""
    given = [f"{a}{b}" for a in ("Anna", "Berta", "Carla", "Dora", "Erika", "Frida") for b in ("", "lie", "bel", "rose", "line")]
    family = [f"{a}{b}" for a in ("Schmidt", "Keller", "Vogel", "Braun") for b in ("", "er", "mann")]
    docs = [(i, f"Frau {g} {f} came. Later {f} left, and {g} {f} too. Dr {g} {f} wrote.") for i, (g, f) in enumerate((g, f) for g in given for f in family)]
    docs += [(1000, "Mr O'Neil met Herr Schmidt."), (1001, None), (1002, "Anna Schmidt is named by nobody")]
    df = spark.createDataFrame(docs, "doc_id long, text string")
    got = {r.doc_id: r for r in pii.replace_entities(df, key=b"k", log_col="log").collect()}
    full, last = {}, {}
    for i, (g, f) in enumerate((g, f) for g in given for f in family):
        log = [(x.found, x.surrogate) for x in got[i].log]
        assert [x[0] for x in log] == [f"{g} {f}", f, f"{g} {f}", f"{g} {f}"] and len({x[1] for x in log if " " in x[0]}) == 1
        assert log[0][1].split()[1] == log[1][1]
        full[f"{g} {f}"] = log[0][1]
        last.setdefault(f, set()).add(log[1][1])
    assert len(set(full.values())) == len(full) and all(len(x) == 1 for x in last.values()) and len(set.union(*last.values())) == len(family)
    assert not set(full.values()) & set(full) and "O'Neil" not in got[1000].text and got[1000].log[1].surrogate in last["Schmidt"]
    assert got[1001].text is None and got[1002].text == "Anna Schmidt is named by nobody"


def test_surrogates_stay_distinct(spark, monkeypatch):
    df = spark.createDataFrame([(i, f"write to {c}{d}@b.co") for i, (c, d) in enumerate((c, d) for c in "abcdefghij" for d in range(10))], "doc_id long, text string")
    first = pii.replace_entities(df, log_col="log").select("doc_id", "text", F.col("log")[0]["surrogate"].alias("s")).collect()
    assert len({r.s for r in first}) == 100 and not {r.s for r in first} & {f"{c}{d}@b.co" for c in "abcdefghij" for d in range(10)}
    monkeypatch.setattr(pii, "BROADCAST_ROWS", -1)
    again = pii.replace_entities(df, log_col="log").select("doc_id", "text", F.col("log")[0]["surrogate"].alias("s")).collect()
    assert sorted(again) == sorted(first)


def test_archives(spark):
    big = "<p>é</p>" * 200
    rows = [(1, "http://a/x", big), (9, "http://b", big), (4, "http://c", "short"), (5, "http://d", "short"), (6, None, None), (None, "http://[", "y" * 2000), (7, "line\nbreak", "z\r\n\r\n")]
    df = spark.createDataFrame(rows, "page_id long, url string, html string")
    got = {r.page_id: r for r in warc.round_trip(df).collect()}
    assert len(got) == 7 and (got[1].record_type, got[1].refers_to) == ("revisit", 9)
    assert all(got[i].record_type == "response" and got[i].refers_to is None for i in (9, 4, 5, 6, None, 7))
    for i, _, h in rows:
        b = (h or "").encode()
        assert (got[i].payload_bytes, got[i].payload_digest) == (len(b), hashlib.sha1(b).hexdigest())
    assert warc.round_trip(df.limit(0)).count() == 0


def test_transactions_hold_all_records(spark):
    df = spark.createDataFrame([(1, "http://a/x?y", "<b>hi</b>")], "page_id long, url string, html string")
    folder = warc.shared_folder(spark, "t")
    row = warc.transactions(warc.read_archives(warc.write_archives(df, folder), folder)).first()
    assert bytes(row.response.payload) == b"<b>hi</b>" and row.request.body.startswith("GET /x") and row.page_id == 1


def test_toxicity(spark, empty):
    r = np.random.default_rng(0)
    docs = [(i, text_of(i, 60) + (" you idiot moron" if i % 5 == 0 else "")) for i in range(400)] + [(1000, None), (1001, "")]
    d = spark.createDataFrame(docs, "doc_id long, text string")
    labels = spark.createDataFrame([(i, int(i % 5 == 0)) for i in range(400)], "doc_id long, toxic int")
    m = toxicity.trained(d, labels)
    got = {x.doc_id: x for x in toxicity.scores(d, m).collect()}
    assert len(got) == 402 and all(0 <= x.score <= 1 and x.predicted == (x.score >= 0.5) for x in got.values())
    held = [x for x in got.values() if x.held_out]
    assert all((zlib.crc32(str(i).encode()) % 5 == 0) == x.held_out for i, x in got.items())
    assert np.mean([x.predicted == (x.doc_id % 5 == 0 and x.doc_id < 1000) for x in held]) > 0.95
    slots, _ = toxicity.features(docs[0][1])
    assert m.logit(slots) == pytest.approx(float(m.pooled(slots)[0] @ m.out + m.bias), abs=1e-4)
    again = toxicity.trained(d.orderBy(F.desc("doc_id")).repartition(5), labels)  # dealt otherwise, the same weights
    assert all((a == b).all() for a, b in zip((m.embedding, m.out, m.shift, *m.filters), (again.embedding, again.out, again.shift, *again.filters)))
    none = toxicity.trained(empty, labels.limit(0))
    assert toxicity.scores(empty, none).count() == 0 and toxicity.keep_clean(d, m).count() < 402
    assert r is not None


def test_packing(spark, odd, empty):
    got = packing.pack(odd, vocabulary("word_bpe_49k.json"), window=256).toPandas()
    from tokenizers import Tokenizer

    tok = Tokenizer.from_file(vocabulary("word_bpe_49k.json"))
    want = collections.Counter()
    for r in odd.collect():
        ids = tok.encode(r.text or "", add_special_tokens=False).ids + [1]
        for s in range(0, len(ids), 256):
            want[(r.doc_id, s, len(ids[s : s + 256]), zlib.crc32(np.array(ids[s : s + 256], "<u4").tobytes()), len(ids))] += 1
    have = collections.Counter((None if d != d else int(d), s, n, c, t) for d, s, n, c, t in got[["doc_id", "start", "length", "ids_crc32", "doc_tokens"]].itertuples(index=False))
    assert have == want
    for _, g in got.sort_values("offset").groupby("sequence_id"):
        assert g.offset.tolist() == [0, *np.cumsum(g.length)[:-1]] and g.length.sum() <= 256
    assert packing.pack(empty, vocabulary("word_bpe_49k.json")).count() == 0


def test_sum_of_squares_choice():
    r, s = np.random.default_rng(1), packing.SumOfSquares(16)
    levels: dict[int, int] = {}
    for n in r.integers(1, 17, 300):
        count = collections.Counter(v for v in levels.values() if v < 16)
        square = lambda c: sum(v * v for v in c.values())
        best = []
        for h in [0, *sorted(set(count))]:
            if h + n <= 16 and (n < 16 or h == 0):
                c = count.copy()
                c[h] -= h > 0
                if h + n < 16:
                    c[h + n] += 1
                best.append(square(c))
        w, at = s.place(int(n))
        assert levels.get(w, 0) == at
        levels[w] = at + int(n)
        assert square(collections.Counter(v for v in levels.values() if v < 16)) == min(best)


def test_piece_codec(spark, odd, empty):
    import sentencepiece

    lib = sentencepiece.SentencePieceProcessor(model_file=vocabulary("piece_bpe_32k.model"))
    c = piece_codec.PieceCodec(vocabulary("piece_bpe_32k.model"), compare=False)
    r = np.random.default_rng(5)
    texts = ["", " ", "  a  b\n\tc€𝄞", "▁x ▁", "<s>hi</s>", "日本語 テキスト", "a" * 500, "\r\n x", *("".join(r.choice(list("abcdeé ▁\n012 xyz日"), 40)) for _ in range(300))]
    for t in texts:
        ids = lib.encode(t, add_bos=True, add_eos=True)
        assert c.encode(t) == ids and c.decode(ids) == lib.decode(ids)
    got = collections.Counter((x.doc_id, x.n_tokens, x.ids_sha256, x.decoded_sha256) for x in piece_codec.encode_decode(odd, vocabulary("piece_bpe_32k.model")).collect())
    want = collections.Counter()
    for x in odd.collect():
        ids = lib.encode(x.text or "", add_bos=True, add_eos=True)
        want[(x.doc_id, len(ids), hashlib.sha256(np.array(ids, "<u4").tobytes()).hexdigest(), hashlib.sha256(lib.decode(ids).encode()).hexdigest())] += 1
    assert got == want and piece_codec.encode_decode(empty, vocabulary("piece_bpe_32k.model")).count() == 0


def test_sharding(spark, odd, empty):
    df = spark.range(3000).select(F.col("id").alias("doc_id"), F.lit("é").alias("text"))
    tree = sharding.regular_tree(8)
    got = sharding.place(df, tree, sharding.grown(tree, 8)).toPandas()
    assert set(got.shard) == set(range(8)) and (got["size"] == 3).all() and (got.text_crc32 == zlib.crc32("é".encode())).all()
    assert all(sorted(g.slot) == list(range(len(g))) for _, g in got.groupby("shard"))
    moved = got[got.grown_shard != got.shard]
    assert set(moved.grown_shard) == {8} and 200 < len(moved) < 500
    u = lambda node, key: ((xxhash.xxh64_intdigest(f"{node}|{key}".encode(), 42) >> 11) + 0.5) / (1 << 53)
    for d, s in zip(got.doc_id[:50], got.shard[:50]):
        path, node = "", tree
        while isinstance(node, dict):
            name = min(node, key=lambda n: -np.log(u(f"{path}/{n}", d)) / sharding.weight_of(node[n]))
            path, node = f"{path}/{name}", node[name]
        assert int(path.rpartition("/")[2]) == s
    weighed = {"a": {"0": 1.0, "1": 3.0}, "b": {"2": 4.0, "3": 0.0}}
    share = sharding.place(df, weighed).groupBy("shard").count().toPandas().set_index("shard")["count"] / 3000
    assert share[2] == pytest.approx(0.5, abs=0.05) and share[1] == pytest.approx(0.375, abs=0.05) and 3 not in share
    assert sharding.place(odd, tree).count() == 13 and sharding.place(empty, tree).count() == 0


def test_pipeline_stages(spark):
    import corpus_pipeline

    docs = spark.read.parquet("/root/testdata/sf0.001/documents.parquet")
    names = docs.columns
    counts = [docs.count()]
    for name, stage in corpus_pipeline.STAGES:
        docs = corpus_pipeline.written(stage(spark, docs, "/root/testdata/sf0.001"), name)
        counts.append(docs.count())
        assert name == "packing" or docs.columns == names
    assert counts[1] > 0.8 * counts[0] and counts[2] <= counts[1] and counts[3] <= counts[2] and counts[4] == counts[3]


@pytest.fixture(scope="module")
def planted(spark, tmp_path_factory):
    """Documents with known fates, columns whose names the stages use themselves, and their labels."""
    folder = str(tmp_path_factory.mktemp("planted"))
    docs = [(i, text_of(i, 60) + (" you idiot moron" if i % 5 == 0 else "")) for i in range(300)]
    base = text_of(5000, 200)
    docs += [(1000, base), (1001, base + "  "), (1002, base.replace(" ", " x ", 1)), (1003, text_of(5001, 200) + " write to ann@b.example.com"), (1004, None), (1005, ""), (1005, ""), (None, "no id at all here"), (1006, "word " * 3000)]
    rows = [(i, t, "en", "s", 0, 7, "h", b"k", True) for i, t in docs]
    spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long, m long, h string, key binary, kept boolean").write.parquet(f"{folder}/documents.parquet")
    spark.createDataFrame([(i, int(i % 5 == 0)) for i in range(300)], "doc_id long, toxic int").write.parquet(f"{folder}/labels.parquet")
    return folder


def test_planted_documents_meet_their_fates(spark, planted):
    import corpus_pipeline

    docs, left = spark.read.parquet(f"{planted}/documents.parquet"), {}
    names = docs.columns
    for name, stage in corpus_pipeline.STAGES:
        docs = corpus_pipeline.written(stage(spark, docs, planted), name)
        left[name] = docs
        assert name == "packing" or docs.columns == names
    ids = {k: collections.Counter(r.doc_id for r in v.select("doc_id").collect()) for k, v in left.items()}
    clean = {i for i in range(300) if i % 5}
    assert clean <= set(ids["toxicity"]) and sum(i in ids["toxicity"] for i in range(0, 300, 5)) <= 3
    assert 1001 in ids["exact_dedup"] and 1000 not in ids["exact_dedup"] and sum(ids["exact_dedup"][i] for i in (1004, 1005)) == 1
    assert (1001 in ids["near_dedup"]) and 1002 not in ids["near_dedup"] and clean <= set(ids["near_dedup"]) and None in ids["near_dedup"]
    private = {r.doc_id: r.text for r in left["pii"].collect()}
    assert "ann@b.example.com" not in private[1003] and private[1003].startswith(text_of(5001, 200)) and set(ids["pii"]) == set(ids["near_dedup"]) == set(ids["packing"])


def test_stages_take_empty_tables(spark, planted):
    import corpus_pipeline

    empty = spark.read.parquet(f"{planted}/documents.parquet").limit(0)
    assert all(stage(spark, empty, planted).count() == 0 for _, stage in corpus_pipeline.STAGES)
