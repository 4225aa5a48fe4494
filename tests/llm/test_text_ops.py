"""Joins, packing, token store, decontamination, licenses against brute force on small tables with odd rows."""

import random
import re
import textwrap
import zlib

import numpy as np
import pytest

from catchment.llm import decontaminate, licenses, ngram_join, packing, token_store
from catchment.llm.common import hashed_texts, word_hashes
from catchment.llm.tokens import WordEncoder

KIND = "doc_id long, text string, key string, n long, score double, label string"


def docs(spark, texts, first=0):
    """Documents with columns whose names also occur inside the operators."""
    return spark.createDataFrame([(first + i, t, "k", 1, 0.5, "x") for i, t in enumerate(texts)], KIND)


def odd_texts():
    rng = random.Random(5)
    words = [f"w{i}" for i in range(60)]
    base = [" ".join(rng.choice(words) for _ in range(n)) for n in (3, 5, 8, 9, 12, 30, 30, 60, 200)]
    out = [None, "", "   ", "one", "ONE", "one two three", "One  Two\tthree\n"]
    for t in base:
        out += [t, t, t.upper()]
        w = t.split()
        for k in range(4):
            v = list(w)
            v[rng.randrange(len(v))] = f"x{k}"
            out.append(" ".join(v))
        out.append(t + " tail")
    return out + ["same shared line of words again and again " * 40 + f"end{i}" for i in range(12)]


def brute_components(texts, width=5, num=80, den=100):
    sets = []
    for t in texts:
        w = [] if t is None else t.encode().lower().split()
        sets.append({tuple(w[k : k + width]) for k in range(max(1, len(w) - width + 1))} if w else set())
    owner = list(range(len(texts)))

    def find(x):
        while owner[x] != x:
            x = owner[x]
        return x

    for a in range(len(texts)):
        for b in range(a + 1, len(texts)):
            common = len(sets[a] & sets[b])
            if sets[a] and sets[b] and den * common >= num * (len(sets[a]) + len(sets[b]) - common):
                x, y = find(a), find(b)
                owner[max(x, y)] = min(x, y)
    return {i: (len(sets[i]), find(i)) for i in range(len(texts))}


@pytest.mark.parametrize("light", [0, 12])
def test_join_equals_brute_force(spark, light):
    texts = odd_texts()
    got = ngram_join.jaccard_join(docs(spark, texts), largest_light=light, cell=4, entry_cost=1e9 if light else 12.0).collect()
    assert {r["doc_id"]: (r["n_shingles"], r["component_id"]) for r in got} == brute_components(texts)
    assert any(r["is_light"] for r in got) == bool(light)


def test_join_odd_rows(spark):
    t = "a b c d e f g h"
    frame = spark.createDataFrame([(None, t, "x"), (7, t, "x"), (7, t, "x"), (3, t, "y"), (9, None, None)], "doc_id long, text string, u string")
    got = sorted(ngram_join.jaccard_join(frame).collect(), key=str)
    assert sorted((r["doc_id"] is None, r["component_id"]) for r in got if r["doc_id"] != 9) == [(False, 3), (False, 3), (False, 3), (True, None)]
    kept = ngram_join.keep_one(frame)
    assert kept.columns == frame.columns and sorted(str(r["doc_id"]) for r in kept.collect()) == ["3", "9", "None"]
    assert ngram_join.jaccard_join(frame.limit(0)).count() == 0


def test_boundary_follows_cost():
    sizes = {n: 100 for n in range(1, 40)}
    assert ngram_join.boundary(sizes, 80, 100, 0.01, 12) == 0
    assert ngram_join.boundary(sizes, 80, 100, 1e6, 12) == 12
    assert 0 < ngram_join.boundary(sizes, 80, 100, 12.0, 12) < 12


def test_word_hashes_see_only_words():
    assert (word_hashes(b"ab  cd") == word_hashes(b"ab cd")).all()
    h, at = hashed_texts([b"a b", b"", b" b "])
    assert at.tolist() == [0, 2, 2, 3] and h[1] == h[2]


def test_encoder_equals_library():
    e = WordEncoder(packing.vocabulary_path(), slots=1 << 10, parts=50)
    rng = random.Random(1)
    alphabet = "aA'sStT re1 ½é́ÉßÀ \n\t\r $%.,<|>ſΣσςİi日 \x1c\u0085"
    texts = ["".join(rng.choice(alphabet) for _ in range(rng.randrange(80))) for _ in range(600)]
    texts += ["<|endoftext|>a", "it's we'll", "🙂 x", "ab" * 3000]
    for lo in range(0, len(texts), 100):
        some = texts[lo : lo + 100]
        ids, sizes = e.encode([t.encode() for t in some])
        want = [x.ids for x in e.lib.encode_batch_fast(some, add_special_tokens=False)]
        assert ids.tolist() == [i for w in want for i in w] and sizes.tolist() == [len(w) for w in want]


def library_ids(texts):
    from tokenizers import Tokenizer

    t = Tokenizer.from_file(packing.vocabulary_path())
    return [np.array([*t.encode(x or "", add_special_tokens=False).ids, 1], "<u4") for x in texts]


def test_packing(spark):
    rng = random.Random(2)
    texts = [None, "", "word " * 9000] + [" ".join(f"t{rng.randrange(500)}" for _ in range(rng.randrange(1, 700))) for _ in range(80)]
    got = packing.pack(docs(spark, texts).repartition(7), packing.vocabulary_path(), fan=2).collect()
    want = {}
    for i, ids in enumerate(library_ids(texts)):
        for k in range(0, len(ids), 4096):
            piece = ids[k : k + 4096]
            want[i, k // 4096] = (k, len(piece), zlib.crc32(piece))
    assert {(r["doc_id"], r["piece"]): (r["start"], r["length"], r["ids_crc32"]) for r in got} == want
    bins = {}
    for r in got:
        bins.setdefault(r["sequence_id"], []).append((r["offset"], r["length"]))
    for spans in bins.values():
        at = 0
        for offset, length in sorted(spans):
            assert offset == at
            at += length
        assert at <= 4096
    assert len(bins) <= 1.15 * sum(r["length"] for r in got) / 4096 + 1


def test_best_fit_takes_the_tightest_gap():
    bins, offsets, fills = packing.best_fit(np.array([6, 5, 4, 3, 2]), 10)
    assert fills.tolist() == [10, 10] and bins[0] == bins[2]


def test_packing_empty_and_repeated(spark):
    assert packing.pack(docs(spark, ["x"]).limit(0), packing.vocabulary_path()).count() == 0
    twice = spark.createDataFrame([(1, "a"), (1, "a"), (None, "b")], "doc_id long, text string")
    assert packing.pack(twice, packing.vocabulary_path()).count() == 3


def test_token_store_round_trip(spark):
    texts = [None, "", "z " * 5000, "same", "same"] + [f"text number {i}" for i in range(60)]
    frame = docs(spark, texts, first=-2).unionByName(spark.createDataFrame([(5, "again", "k", 1, 0.1, "x"), (None, "no id", "k", 1, 0.1, "x")], KIND))
    store, records = token_store.write_store(frame, packing.vocabulary_path(), part_keys=16)
    rows = sorted(((r["doc_id"] is not None, r["doc_id"] or 0, r["text"] or "") for r in frame.collect()), key=lambda r: r)
    got = {(r["start"], r["n_tokens"], r["ids_crc32"]) for r in store.read(records.select("doc_id", "occurrence")).collect()}
    at, want = 0, set()
    for ids in library_ids([r[2] for r in rows]):
        want.add((at, len(ids), zlib.crc32(ids)))
        at += len(ids)
    assert got == want
    absent = spark.createDataFrame([(10**9, 0), (5, 9)], "doc_id long, occurrence long")
    assert store.read(absent).count() == 0
    empty, none = token_store.write_store(frame.limit(0), packing.vocabulary_path())
    assert empty.read(none.select("doc_id", "occurrence")).count() == 0


def test_perfect_hash_is_minimal():
    rng = np.random.default_rng(1)
    h, g = (rng.integers(0, 1 << 63, 5000, dtype=np.uint64) for _ in range(2))
    part = token_store.IndexPart(token_store.index_bytes(h, g, np.arange(5000), np.arange(5000) * 3, np.ones(5000)))
    ok, shard, offset, _ = part.find(h, g)
    assert ok.all() and (shard == np.arange(5000)).all() and (offset == 3 * shard).all()
    assert sorted(part.mph.slots(h, g)) == list(range(5000))
    strangers = rng.integers(0, 1 << 63, (2, 20000), dtype=np.uint64)
    assert part.find(*strangers)[0].mean() < 1e-3


def benchmark(spark, rng):
    vocabulary = [f"q{i}" for i in range(400)]
    items = [[rng.choice(vocabulary) for _ in range(rng.randrange(15, 60))] for _ in range(30)] + [[rng.choice(vocabulary) for _ in range(130)]]
    frame = spark.createDataFrame([(i, " ".join(w)) for i, w in enumerate(items)] + [(98, None), (99, "...")], "item_id long, text string")
    return items, frame


def test_decontamination(spark):
    rng = random.Random(7)
    items, frame = benchmark(spark, rng)
    noise = [f"n{i}" for i in range(3000)] + [f"q{i}" for i in range(400)]
    clean = [" ".join(rng.choice(noise) for _ in range(rng.randrange(1, 400))) for _ in range(80)]
    around = lambda words: " ".join(rng.choice(noise) for _ in range(rng.randrange(100))) + " " + " ".join(words) + " " + " ".join(rng.choice(noise) for _ in range(rng.randrange(100)))
    exact = [around(w).upper() for w in items]
    paraphrased = [around([x if k % 5 else "other" for k, x in enumerate(w[:-4])] + w[-4:]) for w in items]
    texts = clean + exact + paraphrased + [None, "", "..."]
    found = decontaminate.with_matches(docs(spark, texts), frame).collect()
    got = {(r["doc_id"], m["item_id"]) for r in found for m in r["matches"]}
    n, k = len(clean), len(items)
    assert got == {(n + i, i) for i in range(k)} | {(n + k + i, i) for i in range(k)}
    kept = decontaminate.drop_contaminated(docs(spark, texts), frame)
    assert kept.columns == docs(spark, ["x"]).columns and kept.count() == n + 3
    assert decontaminate.drop_contaminated(docs(spark, clean), frame.limit(0)).count() == n
    assert decontaminate.with_matches(docs(spark, clean).limit(0), frame).count() == 0


def test_decontamination_finds_every_copy_of_many_passages(spark):
    rng = random.Random(9)
    vocabulary = [f"q{i}" for i in range(5000)]
    items = [[rng.choice(vocabulary) for _ in range(rng.randrange(15, 60))] for _ in range(2000)]
    frame = spark.createDataFrame([(i, " ".join(w)) for i, w in enumerate(items)], "item_id long, text string")
    noise = lambda: [rng.choice(vocabulary) if rng.random() < 0.3 else f"n{rng.randrange(9000)}" for _ in range(rng.randrange(100))]
    texts = [" ".join(noise() + items[i] + noise()) for i in range(0, 2000, 5)]
    found = decontaminate.with_matches(docs(spark, texts), frame).collect()
    assert all(5 * r["doc_id"] in {m["item_id"] for m in r["matches"]} for r in found) and len(found) == 400


def test_decontamination_finds_a_passage_that_a_third_of_the_rows_hold(spark):
    rng = random.Random(10)
    items, frame = benchmark(spark, rng)
    k = min(range(len(items)), key=lambda i: len(items[i]))
    noise = lambda: [f"n{rng.randrange(9000)}" for _ in range(rng.randrange(50, 100))]
    texts = [" ".join(noise() + (items[k] if i % 3 == 0 else []) + noise()) for i in range(600)]
    found = decontaminate.with_matches(docs(spark, texts), frame).collect()
    assert {(r["doc_id"], m["item_id"]) for r in found for m in r["matches"]} == {(i, k) for i in range(0, 600, 3)}


def test_subsequence_against_table():
    rng = random.Random(3)
    for _ in range(200):
        a, b = ([rng.choice("abcd") for _ in range(rng.randrange(1, 20))] for _ in range(2))
        table = [[0] * (len(b) + 1) for _ in range(len(a) + 1)]
        for i, x in enumerate(a):
            for j, y in enumerate(b):
                table[i + 1][j + 1] = table[i][j] + 1 if x == y else max(table[i][j + 1], table[i + 1][j])
        assert decontaminate.common_subsequence(a, b) == table[-1][-1]


def test_latent_basis_spans_the_passages(spark):
    items, frame = benchmark(spark, random.Random(8))
    (index,) = decontaminate.build_indexes(docs(spark, ["n1 q2 q3", None]), frame, rank=64)
    assert np.allclose(index.basis.T @ index.basis, np.eye(index.basis.shape[1]), atol=1e-3)
    lengths = np.linalg.norm(index.segments, axis=1)
    assert (lengths > 0.98).all()


def test_licenses_against_all_pairs(spark):
    rng = random.Random(4)
    lines = [t.text for t in licenses.TEMPLATES] + ["Licensed under CC BY-NC 4.0.", "ALL RIGHTS\nRESERVED", "cc by cc by", "the GNU General\nPublic License!", "mit license released under the", "nothing here"]
    texts = [None, "", "..."]
    for _ in range(150):
        w = rng.choice(lines).split(" ")
        for _ in range(rng.randrange(4)):
            w[rng.randrange(len(w))] = rng.choice(["x", "the", "license", "y"])
        texts.append("\n".join([" ".join(w), rng.choice(lines), "tail of mine"]))
    got = {r["doc_id"]: r["license"] for r in licenses.scan(docs(spark, texts)).collect()}
    words = lambda s: re.findall(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+", "".join(c.lower() if "A" <= c <= "Z" else c for c in s or ""))
    for i, text in enumerate(texts):
        w, places, base = words(text), [], set()
        for phrase, label in licenses.PHRASES.items():
            p = phrase.split()
            here = [k for k in range(len(w)) if w[k : k + len(p)] == p]
            places += here
            base |= {label} if here else set()
        blocks = []
        for number, line in enumerate((text or "").split("\n")):
            for t in licenses.TEMPLATES:
                s, b = set(words(t.text)), set(words(line))
                if set(words(t.must)) <= b and len(s & b) >= 0.85 * len(s) - 1e-9:
                    blocks.append((number, t.label, len(s & b) / len(s)))
        r = got[i]
        assert (r["n_words"], r["n_base"], r["first_word"], r["last_word"]) == (len(w), len(places), min(places, default=None), max(places, default=None))
        assert r["base_labels"] == ",".join(sorted(base)) and r["labels"] == ",".join(sorted(base | {b[1] for b in blocks}))
        assert sorted((m["line"], m["label"], m["containment"]) for m in r["matches"]) == sorted(blocks)
        assert 0 <= r["score"] <= 1


def test_licenses_wrapped_over_lines_and_without_a_distinctive_word(spark, tmp_path):
    wrapped = ["intro\n\n" + "\n".join(f" * {x}" for x in textwrap.wrap(t.text, 40)) + "\n *\n * tail" for t in licenses.TEMPLATES]
    texts = wrapped + [licenses.TEMPLATES[1].text.replace("charge", "cost"), "released under\n\nthe MIT license", None]
    docs(spark, texts).write.parquet(f"{tmp_path}/documents.parquet")
    got = {r["doc_id"]: r for r in licenses.op4_license_scan(spark, str(tmp_path)).collect()}
    n = len(wrapped)
    assert all(t.label in got[i]["labels"].split(",") for i, t in enumerate(licenses.TEMPLATES))
    assert all(t.label in got[i]["distinctive_labels"].split(",") for i, t in enumerate(licenses.TEMPLATES))
    assert (got[n]["labels"], got[n]["distinctive_labels"]) == ("mit", "") and 0.85 <= got[n]["score"] < 1
    assert got[n + 1]["labels"] == got[n + 2]["labels"] == ""


def true_links(texts, width=5, num=80, den=100):
    sets = []
    for t in texts:
        w = [] if t is None else t.encode().lower().split()
        sets.append({tuple(w[k : k + width]) for k in range(max(1, len(w) - width + 1))} if w else set())
    out = [0] * len(texts)
    for a in range(len(texts)):
        for b in range(len(texts)):
            common = len(sets[a] & sets[b])
            out[a] += a != b and bool(sets[a]) and bool(sets[b]) and den * common >= num * (len(sets[a]) + len(sets[b]) - common)
    return out


def test_all_links_are_counted(spark):
    rng = random.Random(31)
    base = [f"b{i}" for i in range(70)]
    near = []
    for k in range(60):
        w = list(base)
        for _ in range(rng.choice((1, 1, 2, 3))):
            w[rng.randrange(len(w))] = f"y{k}"
        near.append(" ".join(w))
    texts = odd_texts() + near + near[:5]
    got = {r["doc_id"]: r["n_links"] for r in ngram_join.jaccard_join(docs(spark, texts)).collect()}
    assert [got[i] for i in range(len(texts))] == true_links(texts)


@pytest.mark.parametrize("seed", [1, 2])
def test_block_links(seed):
    rng = np.random.default_rng(seed)
    pool = rng.integers(0, 1 << 62, 400).astype(np.int64)
    sets = [np.unique(rng.choice(pool[:60] if k % 3 else pool, rng.integers(5, 60))) for k in range(150)]
    link = ngram_join.block_links(sets[:90], sets[90:], 40, 100)
    want = [[100 * len(set(a.tolist()) & set(b.tolist())) >= 40 * len(set(a.tolist()) | set(b.tolist())) for b in sets[90:]] for a in sets[:90]]
    assert (link == np.array(want)).all() and link.any()
    own = ngram_join.block_links(sets, None, 40, 100)
    assert (own == own.T).all() and not own.diagonal().any()
    assert (own[:90, 90:] == link).all()


def test_repeats_are_counted_in_bounded_memory():
    rng = np.random.default_rng(3)
    counts = {}
    r = ngram_join.Repeats(bits=16, held=64, table=100)
    told = {}
    for _ in range(200):
        tokens = np.unique(rng.zipf(1.6, 40).astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15))
        for t in tokens.tolist():
            counts[t] = counts.get(t, 0) + 1
        full = r.add(tokens)
        assert len(r.tokens) <= 100 + 64 and r.size <= 64 + 40
        if full:
            for t, c in zip(*(x.tolist() for x in full)):
                told[t] = told.get(t, 0) + c
    for t, c in zip(*(x.tolist() for x in r.flush())):
        told[t] = told.get(t, 0) + c
    top = sorted(counts, key=counts.get)[-10:]
    assert all(t in told and told[t] >= counts[t] for t in top)


def test_packing_where_partitions_hold_one_kind(spark):
    """Long documents in half of the partitions, short ones in the others: no looser than one best-fit over all pieces."""
    rng = random.Random(6)
    texts = ["word " * rng.randrange(2300, 2900) for _ in range(40)] + ["word " * rng.randrange(300, 1500) for _ in range(120)]
    rows = spark.createDataFrame([(i, t) for i, t in enumerate(texts)], "doc_id long, text string").repartitionByRange(8, "doc_id")
    out = packing.pack(rows, packing.vocabulary_path(), node_pieces=32).collect()
    _, _, fills = packing.best_fit(np.array([r["length"] for r in out], np.int64), 4096)
    assert len({r["sequence_id"] for r in out}) <= 1.03 * len(fills)


def test_packing_makes_the_sequences(spark):
    """Every sequence stands whole, once, as the ids of its pieces in order, also where it is made of bins of several nodes."""
    rng = random.Random(8)
    texts = [None, "", "word " * 9000] + [" ".join(f"t{rng.randrange(500)}" for _ in range(rng.randrange(1, 1500))) for _ in range(120)]
    ids = library_ids(texts)
    for options in ({}, {"node_pieces": 5, "fan": 3}, {"node_pieces": 5, "fan": 3, "carry": 1}):
        found = {}
        for r in packing.pack(docs(spark, texts), packing.vocabulary_path(), **options).collect():
            found.setdefault(r["sequence_id"], []).append(r)
        for rows in found.values():
            rows.sort(key=lambda r: r["offset"])
            want = np.concatenate([ids[r["doc_id"]][r["start"] : r["start"] + r["length"]] for r in rows])
            assert np.frombuffer(rows[0]["sequence_ids"], "<u2").tolist() == want.tolist() and len(want) == rows[0]["sequence_fill"]
            assert all(r["sequence_ids"] is None for r in rows[1:])
        assert sum(r["length"] for rows in found.values() for r in rows) == sum(map(len, ids))
        # level bits: sequences that the tree has put together
        assert any(s >> 58 for s in found) == bool(options)


def test_packing_hands_up_few_bins(spark):
    """A node that may hand up only some bins still loses no sequence where fewer nodes than that lie below it."""
    rng = random.Random(7)
    rows = spark.createDataFrame([(i, "word " * rng.randrange(50, 3000)) for i in range(200)], "doc_id long, text string")
    count = lambda carry: packing.pack(rows, packing.vocabulary_path(), node_pieces=8, fan=3, carry=carry).select("sequence_id").distinct().count()
    assert count(40) == count(1 << 16)


def brute_matches(texts, passages, loose=0.6, strict=0.75, answer=4):
    """Every text against every passage by the acceptance rule alone, over all its stretches."""
    out = set()
    for i, t in enumerate(texts):
        words = decontaminate.split_words((t or "").encode())
        for k, p in passages:
            item = decontaminate.split_words(p.encode())
            if not item or sum(map(set(words).__contains__, item)) < loose * len(item):
                continue
            n, _ = decontaminate.best_region(item, words)
            share = n / len(item)
            told = decontaminate.common_subsequence(item[-answer:], words) >= max(1, len(item[-answer:]) - 1)
            if share >= strict or share >= loose and told:
                out.add((i, k))
    return out


def test_search_against_all_pairs_of_documents_and_passages(spark):
    """More segments than a block and than the rank: exact copies, paraphrases and clean texts, compared with an all-pairs search."""
    rng = random.Random(41)
    words = [f"v{i}" for i in range(900)]
    passages = [(k, " ".join(rng.choice(words) for _ in range(rng.randrange(14, 60)))) for k in range(340)]
    texts = []
    for k in range(0, 340, 4):
        w = passages[k][1].split()
        if k % 8:
            for _ in range(len(w) // 7):
                w[rng.randrange(len(w))] = f"changed{rng.randrange(99)}"
        filler = lambda: " ".join(f"f{rng.randrange(4000)}" for _ in range(rng.randrange(5, 90)))
        texts.append(f"{filler()} {' '.join(w)} {filler()}")
    texts += [" ".join(f"f{rng.randrange(4000)}" for _ in range(120)) for _ in range(40)] + [None, ""]
    rows = spark.createDataFrame([(i, t) for i, t in enumerate(texts)], "doc_id long, text string")
    bench = spark.createDataFrame(passages, "item_id long, text string")
    found = decontaminate.with_matches(rows, bench, rank=64).selectExpr("doc_id", "explode(matches) m").select("doc_id", "m.item_id", "m.cosine").collect()
    got, want = {(r["doc_id"], r["item_id"]) for r in found}, brute_matches(texts, passages)
    assert got <= want and len(got) >= 0.97 * len(want)
    assert {(i, 4 * i) for i in range(0, 85, 2)} <= got
    assert all(-1e-6 <= r["cosine"] <= 1 + 1e-6 for r in found)


def test_bitmaps_bound_the_overlap():
    rng = np.random.default_rng(5)
    for _ in range(300):
        n = int(rng.integers(1, 400))
        a = np.unique(rng.integers(0, 1 << 62, n).astype(np.uint64))
        b = np.unique(np.concatenate((a[: int(len(a) * rng.random())], rng.integers(0, 1 << 62, int(rng.integers(0, n + 1))).astype(np.uint64))))
        if not len(b) or not 0.8 <= len(a) / len(b) <= 1.25:
            continue
        x, y = ngram_join.set_bitmap(a), ngram_join.set_bitmap(b)
        fold = lambda m, other: m[: len(m) // 2] | m[len(m) // 2 :] if len(m) > len(other) else m
        x, y = fold(x, y), fold(y, x)
        assert len(x) == len(y)
        apart = int(np.bitwise_count((x ^ y).view(np.uint64)).sum())
        assert 2 * len(np.intersect1d(a, b)) <= len(a) + len(b) - apart
