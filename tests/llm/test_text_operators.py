"""Dedup, quality, decontamination, encoding and the pipeline against brute force."""

import hashlib
import math
import random

import numpy as np
import pytest
import tiktoken
import xxhash
from pyspark.sql import functions as F

import corpus_pipeline
from sparsewire.llm import byte_bpe, decontaminate, rule_ensemble, simhash_dedup, suffix_dedup
from sparsewire.llm.common import NO_ID, connected_components
from sparsewire.llm.suffix_array import permuted_common_prefixes, suffix_array


def frame(spark, schema, texts, ids=None):
    ids = range(len(texts)) if ids is None else ids
    return spark.createDataFrame([(i, t, "en", "s", None if t is None else len(t)) for i, t in zip(ids, texts)], schema)


@pytest.fixture(scope="module")
def small_docs(spark, sf):
    return spark.read.parquet(f"{sf}/documents.parquet")


# ---- suffix arrays (2)


def test_suffix_arrays_and_prefixes():
    rng = np.random.default_rng(0)
    for n in range(1, 120):
        t = np.append(np.tile(rng.integers(1, 4, rng.integers(1, 5)), 9) if n % 5 == 0 else rng.integers(1, rng.integers(2, 6), n), 0)
        s = t.tolist()
        want = sorted(range(len(s)), key=lambda i: s[i:])
        got = suffix_array(t)
        assert got.tolist() == want
        p = permuted_common_prefixes(t.astype(np.uint16), got)
        for a, b in zip(want, want[1:]):
            k = 0
            while max(a, b) + k < len(s) and s[a + k] == s[b + k]:
                k += 1
            assert p[b] == k


def brute_repeats(rows):
    """(id, text) rows; ids None come last, equal ids are not smaller."""
    first: dict[bytes, int] = {}
    key = lambda i: NO_ID if i is None else i
    for i, t in rows:
        b = (t or "").encode()
        for p in range(len(b) - 49):
            first[b[p : p + 50]] = min(first.get(b[p : p + 50], NO_ID), key(i))
    out = []
    for i, t in rows:
        b = (t or "").encode()
        gone = bytearray(len(b))
        for p in range(len(b) - 49):
            if first[b[p : p + 50]] < key(i):
                gone[p : p + 50] = b"\1" * 50
        kept = bytes(x for x, g in zip(b, gone) if not g)
        out.append((-1 if i is None else i, len(b), sum(gone), sum(g and (k == 0 or not gone[k - 1]) for k, g in enumerate(gone)), hashlib.sha256(kept).hexdigest()))
    return sorted(out)


def test_repeats_equal_brute_force(spark, docs_schema, odd_texts):
    rng = random.Random(1)
    shared = "".join(rng.choice("abc é") for _ in range(130))
    texts = odd_texts + [f"{rng.random()} {shared[: rng.randrange(30, 130)]} {rng.random()}" for _ in range(25)] + ["zz" + shared + shared, "q" * 51, "q" * 50, "q" * 49]
    ids = [*range(len(texts) - 3), 3, None, None]
    rows = list(zip(ids, texts))
    got = suffix_dedup.repeats(frame(spark, docs_schema, texts, ids)).collect()
    assert sorted((-1 if r.doc_id is None else r.doc_id, r.n_bytes, r.n_removed, r.n_spans, r.kept_sha256) for r in got) == brute_repeats(rows)


def test_repeats_on_the_table(spark, small_docs):
    rows = [(r.doc_id, r.text) for r in small_docs.collect()]
    got = sorted(tuple(r) for r in suffix_dedup.repeats(small_docs).collect())
    assert got == brute_repeats(rows)


def test_texts_without_repeats(spark, docs_schema):
    s = "é" * 30 + "0123456789" * 6
    d = frame(spark, docs_schema, [s, "head " + s + " tail", None]).withColumn("block", F.lit(7)).withColumn("id", F.lit("x"))
    got = {r.doc_id: r for r in suffix_dedup.without_repeats(d).collect()}
    assert got[0].text == s and got[1].text == "head  tail" and got[1].n_chars == 10 and got[2].text is None and got[1].block == 7
    assert suffix_dedup.without_repeats(d.limit(0)).columns == d.columns and suffix_dedup.repeats(d.limit(0)).count() == 0


# ---- SimHash (9)


def brute_fingerprint(text):
    words = (text or "").encode().lower().split()
    h = [xxhash.xxh64_intdigest(b" ".join(words[i : i + 4]), 42) for i in range(max(1, len(words) - 3))] if words else []
    return sum((sum(x >> k & 1 for x in h) * 2 > len(h)) << k for k in range(64))


def brute_components(fps):
    comp = dict(fps)
    names = {i: i for i in comp}
    for i in comp:
        for j in comp:
            if bin(comp[i] ^ comp[j]).count("1") <= 4:
                a, b = names[i], names[j]
                if a != b:
                    names = {k: min(a, b) if v in (a, b) else v for k, v in names.items()}
    return names


def test_every_four_positions_hold_a_triple():
    from itertools import combinations

    assert len(simhash_dedup.TRIPLES) == len(set(simhash_dedup.TRIPLES)) == 20
    assert all(any(set(t) <= set(q) for t in simhash_dedup.TRIPLES) for q in combinations(range(8), 4))


def test_near_duplicates_equal_brute_force(spark, docs_schema, odd_texts, small_docs):
    texts = odd_texts + [r.text for r in small_docs.limit(60).collect()]
    got = simhash_dedup.near_duplicates(frame(spark, docs_schema, texts).withColumn("fp", F.lit(1))).collect()
    assert {r.doc_id: int(r.fingerprint, 16) for r in got} == {i: brute_fingerprint(t) for i, t in enumerate(texts)}
    assert {r.doc_id: r.component_id for r in got} == brute_components({i: brute_fingerprint(t) for i, t in enumerate(texts)})


def test_links_of_planted_fingerprints(spark):
    rng = random.Random(2)
    base = [rng.getrandbits(64) for _ in range(40)]
    fps = base + [b ^ sum(1 << k for k in rng.sample(range(64), rng.randrange(1, 7))) for b in base for _ in range(3)] + [base[0] ^ sum(1 << k for k in rng.sample(range(12), 3)) for _ in range(150)]
    fps = list(dict.fromkeys(fps))
    rows = spark.createDataFrame([(f - 2**64 if f >= 2**63 else f, i) for i, f in enumerate(fps)], "fp bigint, rep bigint")
    comp = {r.node: r.component for r in connected_components(simhash_dedup.links(rows)).collect()}
    want = brute_components(dict(enumerate(fps)))
    assert {i: comp.get(i, i) for i in want} == want


def test_null_ids_and_one_of_each(spark, docs_schema):
    text = "one two three four five six seven"
    d = frame(spark, docs_schema, [text, text, "other words here now", text], [None, 4, 5, 2])
    assert sorted(-1 if r.doc_id is None else r.doc_id for r in simhash_dedup.keep_one(d).collect()) == [-1, 2, 5]
    assert simhash_dedup.near_duplicates(d).count() == 4 and simhash_dedup.near_duplicates(d.limit(0)).count() == 0


def brute_groups(texts):
    """For each text the first text of its group by five-word similarity 0.8."""
    sets = []
    for t in texts:
        w = (t or "").encode().lower().split()
        sets.append({tuple(w[i : i + 5]) for i in range(max(1, len(w) - 4))} if w else set())
    name = list(range(len(texts)))
    for i in range(len(texts)):
        for j in range(i):
            if name[i] != name[j] and 9 * len(sets[i] & sets[j]) >= 4 * (len(sets[i]) + len(sets[j])):
                old, new = max(name[i], name[j]), min(name[i], name[j])
                name = [new if x == old else x for x in name]
    return name


def test_one_of_each_equals_brute_force_at_similarity(spark, docs_schema, odd_texts, small_docs):
    rng = random.Random(5)
    base = [" ".join(f"w{rng.randrange(5000)}" for _ in range(n)) for n in (30, 60, 120, 300)]
    texts = odd_texts + [r.text for r in small_docs.collect()]
    for t in base:
        for _ in range(70):
            w = t.split()
            for _ in range(rng.randrange(len(w) // 25 + 1)):
                w[rng.randrange(len(w))] = "changed"
            texts.append(" ".join(w))
    rng.shuffle(texts)
    want = sorted(set(brute_groups(texts)))
    assert sorted(r.doc_id for r in simhash_dedup.keep_one(frame(spark, docs_schema, texts)).collect()) == want
    assert simhash_dedup.keep_one(frame(spark, docs_schema, texts).limit(0)).count() == 0


# ---- decontamination (1)


def brute_similarity(words, item, k):
    from collections import Counter

    best, n = 0.0, min(len(item), len(words))
    b = Counter(tuple(item[i : i + k]) for i in range(len(item) - k + 1))
    for s in range(len(words) - n + 1):
        w = words[s : s + n]
        a = Counter(tuple(w[i : i + k]) for i in range(len(w) - k + 1))
        best = max(best, sum((a & b).values()) / max(1, sum((a | b).values())))
    return best


def test_contaminated_equals_brute_force(spark, docs_schema, odd_texts, small_docs, sf):
    bench = spark.read.parquet(f"{sf}/benchmark.parquet")
    items = {r.item_id: r.text for r in bench.collect()}
    rng = random.Random(3)
    texts = odd_texts + [r.text for r in small_docs.collect()]
    for t in list(items.values())[:12]:
        w = t.split()
        w[rng.randrange(len(w))] = "changed"
        texts += ["before it " + t.upper() + "; after", " ".join(w), t + " and " + t]
    extra = spark.createDataFrame([(900, "two words"), (901, ""), (902, None)], bench.schema)
    got = {(r.doc_id, r.item_id): r.similarity for r in decontaminate.contaminated(frame(spark, docs_schema, texts), bench.union(extra)).collect()}
    items |= {900: "two words"}
    want = {}
    split = [decontaminate.words_of(t) for t in texts]
    for i, t in items.items():
        item = decontaminate.words_of(t)
        known = {tuple(item[j : j + min(5, len(item))]) for j in range(len(item) - min(5, len(item)) + 1)}
        for d, w in enumerate(split):
            k = min(5, len(item))
            if any(tuple(w[j : j + k]) in known for j in range(len(w) - k + 1)) and (s := brute_similarity(w, item, k)) >= 0.8:
                want[d, i] = s
    assert got.keys() == want.keys() and all(got[k] == pytest.approx(want[k]) for k in want)
    assert len(want) > 20


def test_clean_documents_stay(spark, docs_schema, sf):
    bench = spark.read.parquet(f"{sf}/benchmark.parquet")
    leak = bench.first().text
    d = frame(spark, docs_schema, ["x " + leak, "clean", None, leak], [1, 2, 3, None])
    assert sorted(r.doc_id for r in decontaminate.keep_clean(d, bench).collect()) == [2, 3]
    assert decontaminate.keep_clean(d, bench.limit(0)).count() == 4 and decontaminate.contaminated(d.limit(0), bench).count() == 0


def test_rows_of_equal_or_no_id_are_judged_alone(spark, docs_schema, sf, monkeypatch):
    bench = spark.read.parquet(f"{sf}/benchmark.parquet")
    leak = bench.first().text
    d = frame(spark, docs_schema, [leak, "clean", "clean too", leak, "clean as well", None], [None, None, 7, 7, 8, None])
    want = ["", "clean", "clean as well", "clean too"]
    assert sorted(r.text or "" for r in decontaminate.keep_clean(d, bench).collect()) == want
    monkeypatch.setattr(decontaminate, "PORTION_BYTES", 4000)
    assert sorted(r.text or "" for r in decontaminate.keep_clean(d, bench).collect()) == want


# ---- byte-level BPE (3)


def test_encoding_equals_the_library(spark, docs_schema, odd_texts, small_docs):
    import public_tokenizers as P

    enc = tiktoken.Encoding("own", pat_str=P.PATTERN, mergeable_ranks=byte_bpe.read_ranks(byte_bpe.vocabulary_path()), special_tokens={})
    texts = odd_texts + ["one more word, " * 80_000, "  two  spaces ", "a \n b", " lead", "trail ", "it's we'LL 'tis", "\u3000wide\u2003space x", "<|endoftext|> a", "tab\tand\r\nline", "a\u00a0b c"] + [r.text for r in small_docs.collect()]
    want = {i: enc.encode_ordinary(t or "") for i, t in enumerate(texts)}
    d = frame(spark, docs_schema, texts).withColumn("ids", F.lit("old"))
    rows = byte_bpe.decode(byte_bpe.encode(d)).collect()
    assert {r.doc_id: r.ids for r in rows} == want
    assert all(bytes(r.decoded).decode() == (texts[r.doc_id] or "") for r in rows)
    for r in byte_bpe.digests(d).collect():
        assert r.n_tokens == len(want[r.doc_id]) and r.ids_sha256 == hashlib.sha256(" ".join(map(str, want[r.doc_id])).encode()).hexdigest()
        assert r.decoded_sha256 == hashlib.sha256((texts[r.doc_id] or "").encode()).hexdigest()
        whole = byte_bpe.codec(byte_bpe.vocabulary_path()).tokenizer.encode(texts[r.doc_id] or "", add_special_tokens=False)
        assert r.offsets_sha256 == hashlib.sha256(np.array(whole.offsets, "<i4").tobytes()).hexdigest()
    spans = byte_bpe.encode(d.where("doc_id = 7"), offsets=True).first()
    assert spans.char_start[0] == 0 and max(spans.char_end) == len(texts[7]) and byte_bpe.digests(d.limit(0)).count() == 0


def test_split_characters_decode():
    c = byte_bpe.codec(byte_bpe.vocabulary_path())
    ids = c.encode(["🎉"])[0]
    assert len(ids) > 1 and c.decode(ids).decode() == "🎉" and c.decode(ids[:1]) == "🎉".encode()[: len(c.decode(ids[:1]))]


# ---- quality (10)


def test_quality_on_held_out_rows(spark, sf):
    sf = sf.replace("0.001", "0.01")
    docs, labels = (spark.read.parquet(f"{sf}/{t}.parquet") for t in ("documents", "labels"))
    rows = rule_ensemble.op10_rule_ensemble_quality(spark, sf).join(labels, "doc_id").where("held_out").toPandas()
    assert ((rows.score >= 0.3) == (rows.predicted == 1)).all() and rows.score.between(0, 1).all()
    assert (rows.predicted == rows.quality).mean() > 0.95
    model = rule_ensemble.train(docs, labels)
    stats = rule_ensemble.with_statistics(docs).toPandas()
    got = rule_ensemble.scores(docs, model).toPandas().set_index("doc_id").score
    want = model.score(stats[list(rule_ensemble.STATS)].to_numpy())
    assert np.allclose(got.loc[stats.doc_id], want)
    assert len(model.rules) < 100


def test_quality_without_labels_and_odd_texts(spark, docs_schema, odd_texts):
    d = frame(spark, docs_schema, odd_texts).withColumn("score", F.lit(9)).withColumn("log_bytes", F.lit(1))
    labels = spark.createDataFrame([(1, None), (2, None)], "doc_id bigint, quality int")
    got = rule_ensemble.scores(d, rule_ensemble.train(d, labels)).collect()
    assert len(got) == len(odd_texts) and all(r.score == pytest.approx(0.5) for r in got)
    wide = d.withColumn("predicted", F.lit("x")).withColumn("a.b", F.lit(2)).withColumn("words share", F.lit(3))
    kept = rule_ensemble.keep_good(wide, labels)
    assert kept.count() == len(odd_texts) and kept.columns == wide.columns and kept.schema == wide.schema
    assert sorted(map(repr, kept.collect())) == sorted(map(repr, wide.collect()))
    assert rule_ensemble.keep_good(wide.limit(0), labels).count() == 0


def plain_statistics(text):
    """The statistics by counting characters and words one at a time."""
    raw = text or b""
    words, n = raw.split(), len(raw)
    out = [math.log(1 + n), math.log(1 + len(words)), sum(len(w) for w in words) / max(1, len(words))]
    for test in (bytes.isupper, bytes.islower, bytes.isdigit, lambda c: c in b" \t", lambda c: c == b"\n", lambda c: c[0] > 127, lambda c: c in b".,;:?", lambda c: c == b"!", lambda c: c == b"|", lambda c: c == b"*", lambda c: c == b"$", lambda c: c == b"%", lambda c: c == b"&", lambda c: c == b"#", lambda c: c in b"\"'()[]{}<>/\\=+-_@^~`"):
        out.append(sum(test(bytes([c])) for c in raw) / max(1, n))
    out.append(len({w for w in words}) / max(1, len(words)))
    out.append(sum(words[i] == words[i + 1] for i in range(len(words) - 1)) / max(1, len(words) - 1))
    out.append(sum(w[-1:] in (b"!", b"|", b"*", b"$", b"%", b"&", b"#", b"^", b"~", b"=", b"+") for w in words) / max(1, len(words)))
    return out


def test_scores_equal_brute_force(spark, docs_schema, odd_texts, small_docs, sf):
    """Statistics, rules and weights one by one, and the conditions that the fitted weights must meet."""
    labels = spark.read.parquet(f"{sf}/labels.parquet")
    model = rule_ensemble.train(small_docs, labels)
    texts = odd_texts + ["long words here! " * 70_000] + [r.text for r in small_docs.limit(40).collect()]
    got = {r.doc_id: r.score for r in rule_ensemble.scores(frame(spark, docs_schema, texts), model).collect()}
    assert model.rules and len(got) == len(texts)
    for i, t in enumerate(texts):
        x = plain_statistics(None if t is None else t.encode())
        total = model.bias
        for rule, w in model.rules:
            if all((x[k] > cut) == above for k, above, cut in rule):
                total += w
        assert got[i] == pytest.approx(1 / (1 + math.exp(-total)), abs=1e-9), i


def test_lasso_meets_its_conditions():
    """At the minimum each weight's slope equals the penalty, and is no larger where the weight is zero."""
    rng = np.random.default_rng(3)
    z = rng.integers(0, 2, (300, 8)).astype(float)
    y = (rng.random(300) < 1 / (1 + np.exp(1 - 2 * z[:, 0] + 1.5 * z[:, 3]))).astype(float)
    bias, w = rule_ensemble.lasso_logistic(z, y, 0.02, 20_000)
    a = (z - z.mean(axis=0)) / z.std(axis=0)
    slope = a.T @ (1 / (1 + np.exp(-(z @ w + bias))) - y) / len(y)
    assert np.allclose(slope[w != 0], -0.02 * np.sign(w[w != 0]), atol=1e-4) and (np.abs(slope[w == 0]) <= 0.02 + 1e-4).all()
    assert abs((1 / (1 + np.exp(-(z @ w + bias))) - y).mean()) < 1e-4 and np.count_nonzero(w) < 8


def test_lasso_drops_useless_rules():
    rng = np.random.default_rng(8)
    z = rng.integers(0, 2, (400, 12)).astype(float)
    y = (z[:, 0] + z[:, 1] >= 1).astype(float)
    _, w = rule_ensemble.lasso_logistic(z, y, 0.05)
    assert abs(w[0]) > 0.5 and abs(w[1]) > 0.5 and np.count_nonzero(w[2:]) == 0


# ---- texts of a megabyte and more


def test_very_long_texts(spark, docs_schema, sf):
    rng = random.Random(9)
    words = [f"w{rng.randrange(40_000)}" for _ in range(220_000)]
    long, other = " ".join(words), " ".join(words[:100_000] + ["changed"] * 5 + words[100_000:])
    bench = spark.read.parquet(f"{sf}/benchmark.parquet")
    item = bench.orderBy("item_id").first()
    texts = [long, "short one", other, long + " " + item.text, "=" * 1_500_000, "=" * 1_200_000 + "x", None]
    d = frame(spark, docs_schema, texts)
    assert len(long) > 1_200_000
    found = {(r.doc_id, r.item_id) for r in decontaminate.contaminated(d, bench).collect()}
    assert found == {(3, item.item_id)} and sorted(r.doc_id for r in decontaminate.keep_clean(d, bench).collect()) == [0, 1, 2, 4, 5, 6]
    got = {r.doc_id: r for r in simhash_dedup.near_duplicates(d).collect()}
    assert {i: int(r.fingerprint, 16) for i, r in got.items()} == {i: brute_fingerprint(t) for i, t in enumerate(texts)}
    assert sorted(r.doc_id for r in simhash_dedup.keep_one(d).collect()) == [0, 1, 4, 5, 6]
    cut = {r.doc_id: (r.n_bytes, r.n_removed) for r in suffix_dedup.repeats(d).collect()}
    assert cut[0] == (len(long), 0) and cut[4] == (1_500_000, 0) and cut[5] == (1_200_001, 1_200_000) and cut[6] == (0, 0)
    # all but the inserted words, of which the first space ends a string of the first text, and all but the item
    assert cut[2] == (len(other), len(other) - 5 * len(" changed") + 1) and cut[3] == (len(texts[3]), len(long))


# ---- pipeline


def test_pipeline_stages_chain(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    assert [n for n, _ in corpus_pipeline.STAGES] == ["quality", "near_duplicates", "repeated_passages", "benchmark_leaks", "byte_bpe"]
    out = corpus_pipeline.run(spark, sf)
    rows = out.toPandas()
    # the same steps by brute force
    labels, bench = (spark.read.parquet(f"{sf}/{t}.parquet") for t in ("labels", "benchmark"))
    good = rule_ensemble.scores(docs, rule_ensemble.train(docs, labels)).where("predicted = 1").join(docs, "doc_id").select(*docs.columns).collect()
    good = sorted(good, key=lambda r: r.doc_id)
    first = [(good[i].doc_id, good[i].text) for i in sorted(set(brute_groups([r.text for r in good])))]
    cut = {r[0]: r for r in brute_repeats(first)}
    assert set(rows.doc_id) <= set(cut)
    dropped = set(cut) - set(rows.doc_id)
    hits = {r.doc_id for r in decontaminate.contaminated(suffix_dedup.without_repeats(spark.createDataFrame(good, docs.schema).where(F.col("doc_id").isin([i for i, _ in first]))), bench).collect()}
    assert dropped == hits
    enc = byte_bpe.codec(byte_bpe.vocabulary_path())
    for r in rows.itertuples():
        assert enc.decode(list(r.ids)).decode() == r.text and r.n_tokens == len(r.ids) and len(r.text.encode()) <= cut[r.doc_id][1] - cut[r.doc_id][2]


def test_tasks_give_memory_back_and_learn_in_bounded_parts(monkeypatch):
    from sparsewire.llm import common

    called = []
    monkeypatch.setattr(common, "give_back", lambda: called.append(1))

    def batches(b):
        yield from b

    assert list(common.tidy(batches)([1, 2])) == [1, 2] and len(called) == 1
    assert common.tidy(lambda t: t)(3) == 3 and common.tidy(lambda t, other: t + other)(3, 4) == 7 and len(called) == 3
    enc, sizes = byte_bpe.Codec(byte_bpe.vocabulary_path(), public_pattern()), []
    learn = enc._learn
    monkeypatch.setattr(enc, "_learn", lambda pieces: sizes.append(len(pieces)) or learn(pieces))
    text = " ".join(f"w{i}" for i in range(20_001))
    assert enc.decode(enc.encode([text])[0]).decode() == text
    assert sum(sizes) == 20_001 and max(sizes) <= 8_000


def public_pattern():
    import public_tokenizers

    return public_tokenizers.PATTERN
