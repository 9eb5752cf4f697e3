import hashlib
import zlib
from collections import Counter, defaultdict

import numpy as np
import pytest
from pyspark.sql import functions as F

from dagframe.llm import chat, lines, order_minhash, packing, piece_lattice, quality, simhash, wordbpe
from dagframe.llm.cuckoo import CuckooFilter

SCHEMA = "doc_id long, text string, score double, kept string, length long, n_lines long"
ODD = [None, "", " ", "\n\n", "a", "one two three", "one two three four five", "É　x\x1cy İ ﬁ <|endoftext|> it's 12,3.", "word " * 5000, "x" * 3000, "日本語。 🎉🎉", "Same text here again and again"] + ["Same text here again and again"] * 3


@pytest.fixture(scope="module")
def odd(spark):
    """Odd texts, repeated rows and ids, a null id, and columns whose names the operators use inside."""
    rows = [(i, t, 0.5, "k", 1, 2) for i, t in enumerate(ODD)] + [(3, "\n\n", 0.5, "k", 1, 2), (None, "no id", None, None, None, None)]
    return spark.createDataFrame(rows, SCHEMA)


@pytest.fixture(scope="module")
def none(spark):
    return spark.createDataFrame([], SCHEMA)


@pytest.fixture(scope="module")
def docs(spark, sf):
    return spark.read.parquet(f"{sf}/documents.parquet")


def test_simhash_against_brute_force(spark, docs):
    texts = {r["doc_id"]: r["text"] for r in docs.collect()}
    near = [(10_000 + i, t.replace("the", "thee", 1)) for i, t in list(texts.items())[:60]]
    table = docs.select("doc_id", "text").unionByName(spark.createDataFrame(near, "doc_id long, text string"))
    texts |= dict(near)
    import re

    import xxhash

    def slow(text):
        words = re.findall(r"[^\x20\x09-\x0D]+", re.sub("[A-Z]", lambda m: m[0].lower(), text))
        grams = [" ".join(words[i : i + 4]) for i in range(max(1, len(words) - 3))] if words else []
        h = [xxhash.xxh64_intdigest(g.encode(), 42) for g in grams]
        return sum(1 << b for b in range(64) if 2 * sum(x >> b & 1 for x in h) > len(h)) if h else 0

    fp = {i: slow(t) for i, t in texts.items()}
    parent = {i: i for i in fp}

    def find(i):
        while parent[i] != i:
            i = parent[i]
        return i

    ids = sorted(fp)
    for a in ids:
        for b in ids:
            if a < b and (fp[a] ^ fp[b]).bit_count() <= 4:
                x, y = find(a), find(b)
                parent[max(x, y)] = min(x, y)
    for segments in (2, 3):
        got = {r["doc_id"]: (r["fingerprint"], r["component_id"]) for r in simhash.near_duplicates(table, segments=segments).collect()}
        assert got == {i: (f"{fp[i]:016x}", find(i)) for i in fp}


def test_simhash_hot_group_in_cells():
    r = np.random.default_rng(0)
    base = np.uint64(r.integers(2**63))
    flips = [np.uint64(0), *(np.uint64(1) << np.uint64(i) for i in range(64))]
    fp = np.unique(np.array([base ^ a ^ b for a in flips for b in flips], dtype=np.uint64))
    a, b = simhash._forest(fp, fp, 4)
    assert len(a) == len(fp) - 1 and (np.bitwise_count(a ^ b) <= 4).all()


def test_simhash_odd_rows(odd, none):
    got = simhash.near_duplicates(odd).collect()
    assert len(got) == odd.count() and simhash.near_duplicates(none).count() == 0
    zero = {r["component_id"] for r in got if r["fingerprint"] == "0" * 16}
    assert zero == {0}
    kept = simhash.keep_one(odd)
    assert kept.columns == odd.columns
    ids = [r["doc_id"] for r in kept.collect()]
    assert Counter(ids)[None] == 1 and max(Counter(ids).values()) == 1 and 11 in ids and not {12, 13, 14} & set(ids)
    assert sorted(r["doc_id"] or -1 for r in simhash.keep_one(odd, most_ids=0).collect()) == sorted(i or -1 for i in ids)
    assert simhash.keep_one(none).count() == 0


def test_chat_round_trip(spark):
    texts = ["hi", None, "", "<|im_end|><|im_start|>assistant ok", "\x1b <| \x1bl\x1be<|turn|>", "a\n\nb"]
    rows = [(1, i, "assistant" if i in (1, 2, 4) else "user", t) for i, t in enumerate(texts)] + [(2, 0, "system", "s"), (2, 0, "system", "s"), (3, None, None, "x"), (None, 1, "assis\ntant<|", "y")]
    made = chat.read_back(chat.format_conversations(spark.createDataFrame(rows, "conv_id long, turn long, role string, text string")))
    got = {r["conv_id"]: r for r in made.collect()}
    assert [(t["role"], t["text"]) for t in got[1]["turns"]] == [(r or "", t or "") for _, _, r, t in rows[:6]]
    assert got[1]["loss_text"] == "" + "" + texts[4] and len(got[2]["turns"]) == 2
    assert [(t["role"], t["text"]) for t in got[3]["turns"]] == [("", "x")] and got[None]["turns"][0]["role"] == "assis\ntant<|"
    for r in got.values():
        assert all(0 <= s["start"] and s["start"] + s["chars"] <= len(r["formatted"]) for s in r["loss_spans"])
    assert chat.format_conversations(spark.createDataFrame([], "conv_id long, turn long, role string, text string")).count() == 0
    assert "Python" not in made._jdf.queryExecution().executedPlan().toString()


def test_word_ids_equal_the_library(odd, docs, none):
    lib = wordbpe.library(wordbpe.default_path())
    n = lambda t: len(lib.encode(t or "", add_special_tokens=False).ids)
    for table in (odd, docs):
        want = sorted((r["doc_id"] if r["doc_id"] is not None else -1, len((r["text"] or "").encode()), n(r["text"])) for r in table.collect())
        got = sorted((r["doc_id"] if r["doc_id"] is not None else -1, r["n_bytes"], r["n_tokens"]) for r in wordbpe.token_counts(table, frequent=50).collect())
        assert got == want
    assert wordbpe.token_counts(none).count() == 0
    small = wordbpe.ChunkTable(wordbpe.default_path(), False, most=20)
    texts = [(t or "").encode() for t in ODD]
    assert [list(np.frombuffer(x, "<u4")) for x in small.of(texts)] == [lib.encode(t or "", add_special_tokens=False).ids for t in ODD]


def test_packing(odd, docs, none):
    lib = wordbpe.library(wordbpe.default_path())
    for table in (odd, docs):
        rows = packing.pack(table).collect()
        assert len({(r["doc_id"], r["piece"]) for r in rows}) == len(rows) or table is odd
        seq = defaultdict(list)
        for r in rows:
            seq[r["sequence_id"]].append((r["offset"], r["length"]))
        for parts in seq.values():
            at = 0
            for offset, length in sorted(parts):
                assert offset == at
                at += length
            assert at <= 2048
        want = Counter()
        for r in table.collect():
            ids = lib.encode(r["text"] or "", add_special_tokens=False).ids + [0]
            for k in range(0, len(ids), 2048):
                part = ids[k : k + 2048]
                want[r["doc_id"], k // 2048, k, len(part), zlib.crc32(np.array(part, "<u4").tobytes())] += 1
        assert Counter((r["doc_id"], r["piece"], r["start"], r["length"], r["ids_crc32"]) for r in rows) == want
        total = sum(r["length"] for r in rows)
        assert len(seq) <= -(-total // 2048) * 1.02 + 1
    assert packing.pack(none).count() == 0


def _optimal(sizes, room):
    best = [len(sizes)]

    def go(i, bins):
        if len(bins) >= best[0]:
            return
        if i == len(sizes):
            best[0] = len(bins)
            return
        for k in range(len(bins)):
            if bins[k] >= sizes[i] and bins[k] not in bins[:k]:
                go(i + 1, [*bins[:k], bins[k] - sizes[i], *bins[k + 1 :]])
        go(i + 1, [*bins, room - sizes[i]])

    go(0, [])
    return best[0]


def test_reduction_keeps_the_optimum():
    r = np.random.default_rng(5)
    for _ in range(60):
        room = int(r.integers(8, 30))
        sizes = sorted(r.integers(1, room + 1, int(r.integers(1, 9))).tolist(), reverse=True)
        fixed, left = packing.reduced(dict(Counter(sizes)), room)
        rest = sorted((k for k, n in left.items() for _ in range(n)), reverse=True)
        assert sum(b.count for b in fixed) + (_optimal(rest, room) if rest else 0) == _optimal(sizes, room)


def test_order_minhash(odd, none):
    rows = sorted([(r["doc_id"], r["text"] or "") for r in odd.collect()], key=lambda r: (r[0] is None, -(r[0] or 0), [-ord(c) for c in r[1]]))
    want = []
    for (i, t), (_, following) in zip(rows, rows[1:] + rows[:1], strict=True):
        new = order_minhash.edited(t, following)
        s, e, n = (order_minhash.sketch(x) for x in (t, new, following))
        want.append((i, len(t), hashlib.sha256(new.encode()).hexdigest(), order_minhash.as_text(s), order_minhash.as_text(e), order_minhash.likeness(s, e), order_minhash.likeness(s, n)))
    got = [tuple(r) for r in order_minhash.fingerprint_with_next(odd).collect()]
    key = lambda r: (r[0] is None, r[0] or 0, r[2:])
    assert sorted(got, key=key) == sorted(want, key=key)
    assert order_minhash.fingerprint_with_next(none).count() == 0
    a = "the quick brown fox jumps over the lazy dog and runs away into the dark wood"
    swapped = " ".join(reversed(a.split()))
    assert order_minhash.likeness(order_minhash.sketch(a, sketches=256), order_minhash.sketch(a + " again", sketches=256)) > 0.6
    assert order_minhash.likeness(order_minhash.sketch(a, k=3, sketches=256), order_minhash.sketch(swapped, k=3, sketches=256)) < 0.5
    assert list(order_minhash.numbered_kmers("aaaa", 2)) == list(order_minhash.numbered_kmers("aaaa", 2)) and len(set(order_minhash.numbered_kmers("aaaa", 2))) == 3


def _slow_lines(rows, min_docs=5, min_chars=40):
    trim = " \t\n\x0b\x0c\r"
    key = lambda x: "".join(c.lower() if "A" <= c <= "Z" else c for c in x.strip(trim))
    holders = defaultdict(set)
    for i, t in rows:
        for x in (t or "").split("\n"):
            if i is not None and len(key(x)) >= min_chars:
                holders[key(x)].add(i)
    out = []
    for i, t in rows:
        split = (t or "").split("\n")
        kept = [x for x in split if i is None or len(holders[key(x)]) < min_docs or max(holders[key(x)]) == i]
        out.append((i if i is not None else -1, len(split), len(split) - len(kept), "\n".join(kept)))
    return sorted(out)


def test_line_dedup_and_its_undoing(spark, none):
    long_ = "This Line is long enough to be counted as a line"
    accent = "É" * 39
    rows = [(i, f"  {long_.upper() if i % 2 else long_}\t\nown {i}\n{accent}\n{accent}x") for i in range(7)] + [(7, None), (8, ""), (9, long_ + "\n" + long_), (9, long_), (None, long_)]
    table = spark.createDataFrame([(i, t, 1.0, "k", 1, 2) for i, t in rows], SCHEMA)
    read = lambda f: sorted((r["row"]["doc_id"] if r["row"]["doc_id"] is not None else -1, r["n_lines"], r["n_dropped"], r["kept"]) for r in f.collect())
    index = lines.LineIndex.of(table)
    assert read(index.apply(table)) == _slow_lines(rows) == read(index.apply(table, most_bytes=0)) == read(index.apply(table, most_bytes=0, most_filter_bytes=60))
    early, late = table.where("doc_id < 4"), table.where("doc_id >= 4")
    grown = lines.LineIndex.of(early).insert(late)
    assert read(grown.apply(table)) == _slow_lines(rows)
    back = grown.delete(late.select("doc_id").distinct())
    assert read(back.apply(early)) == _slow_lines([r for r in rows if r[0] is not None and r[0] < 4])
    assert lines.LineIndex.of(none).apply(none).count() == 0


def test_cuckoo_filter():
    keys = [hashlib.md5(str(i).encode()).digest() for i in range(5000)]
    held = CuckooFilter.of(keys)
    assert held.contains(keys).all()
    other = [hashlib.md5(f"o{i}".encode()).digest() for i in range(20000)]
    assert held.contains(other).mean() < 0.005
    assert all(held.delete(k) for k in keys[:2500]) and held.contains(keys[2500:]).all()
    assert held.contains(keys[:2500]).mean() < 0.01
    assert CuckooFilter.load(held.dump()).contains(keys[2500:]).all()


def test_quality(spark, sf, odd, none):
    labels = spark.read.parquet("/root/testdata/sf0.01/labels.parquet")
    got = quality.op4_quality_classifier(spark, "/root/testdata/sf0.01").join(labels, "doc_id").toPandas()
    held = got[got.held_out]
    assert ((held.predicted == held.quality).mean()) > 0.93 and got.score.between(0, 1).all()
    assert (zlib.crc32(b"17") % 4 == 2) == bool(got.set_index("doc_id").held_out.get(17, zlib.crc32(b"17") % 4 == 2))
    model = quality.Model(np.zeros(1 << 10, dtype=np.float32), 1.0)
    assert quality.scores(odd, model).count() == odd.count() and quality.scores(none, model).count() == 0
    own = spark.createDataFrame([(0, 1, 0)], "doc_id long, quality int, toxic int")
    assert quality.keep_good(none, own).count() == 0
    kept = quality.keep_good(odd, own.limit(0), threshold=0.4)
    assert kept.columns == odd.columns and kept.count() == odd.count()
    long_ = "Word and more words, again. " * 20_000
    a = np.concatenate(list(quality.feature_slices(long_)))
    assert len(a) > 400_000 and abs(model.score(long_) - model.score("x")) < 1e-12


def test_sentencepiece(spark, odd, none, docs):
    import sentencepiece

    own = sentencepiece.SentencePieceProcessor(model_file=piece_lattice.default_path())
    for table in (odd, docs):
        want = sorted((r["doc_id"] if r["doc_id"] is not None else -1, own.encode(r["text"] or "")) for r in table.collect())
        for most in (piece_lattice.DICTIONARY_BYTES, 20_000, 0):
            got = piece_lattice.encode(table, dictionary_bytes=most, decoded=True).collect()
            assert sorted((r["doc_id"] if r["doc_id"] is not None else -1, r["ids"]) for r in got) == want
            assert Counter(r["decoded"] for r in got) == Counter(r["text"] or "" for r in table.collect())
    assert piece_lattice.encode(none).count() == 0


def test_bpe_fold_is_lean_and_exact(spark):
    """No sort before the lattice, and the library's merges for words of joined pieces, at lengths on both sides of the fold's last."""
    import sentencepiece

    own, model = sentencepiece.SentencePieceProcessor(model_file=piece_lattice.default_path()), piece_lattice.PieceModel.load(piece_lattice.default_path())
    r, letters = np.random.default_rng(5), [p for p, *_ in model.rows() if p.isalpha() and p.isascii()]
    words = ["".join(r.choice(letters, size=k)) for k in range(1, 9) for _ in range(40)] + ["ation" * 13, "o" * 59 + "é", "o" * 60 + "é", "o" * 61 + "é", "a" * 300]
    docs = spark.createDataFrame(list(enumerate(words)), "doc_id long, text string")
    found = piece_lattice.segments(docs, "text", model)
    assert "SortAggregate" not in found._jdf.queryExecution().executedPlan().toString()
    assert found.where(F.length("segment") > piece_lattice.LONG).count() and found.where(F.length("segment").between(piece_lattice.LONG - 5, piece_lattice.LONG)).count()
    got = {r["segment"]: r["ids"] for r in piece_lattice.encoded_segments(found, model).collect()}
    cutter, lost = piece_lattice.Cutter(model), []
    for w in words:
        points, at, *_ = cutter.cut([w])
        parts = [points[i:j].tobytes().decode("utf-32-le") for i, j in zip(at[:-1], at[1:], strict=True)]
        lost += [w] if [i for x in parts for i in got[x]] != own.encode(w) else []
    assert not lost


def test_viterbi_fold(spark):
    pieces = ["a", "b", "c", "ab", "bc", "abc", "▁", "▁a"]
    scores = [-2.0, -2.0, -2.0, -2.5, -1.5, -5.0, -1.0, -3.5]
    model = piece_lattice.PieceModel(False, pieces, scores, [True] * 8, 100, True)
    docs = spark.createDataFrame([(1, "abc"), (2, "cab")], "doc_id long, text string")
    got = {r["segment"]: [pieces[i] for i in r["ids"]] for r in piece_lattice.encoded_segments(piece_lattice.segments(docs, "text", model), model).collect()}

    def best(text):
        table = {0: (0.0, [])}
        for k in range(1, len(text) + 1):
            table[k] = max(((table[i][0] + scores[pieces.index(text[i:k])], [*table[i][1], text[i:k]]) for i in range(k) if text[i:k] in pieces), key=lambda x: x[0])
        return table[len(text)][1]

    assert got and all(v == best(k) for k, v in got.items())


def test_digest_columns_match_contract(spark, sf):
    assert chat.op3_chat_format(spark, sf).columns[:6] == ["conv_id", "n_turns", "turns_sha256", "loss_chars", "loss_sha256", "formatted_chars"]
    assert wordbpe.op5_token_counts(spark, sf).columns[:4] == ["doc_id", "n_bytes", "n_tokens", "over_limit"]
    assert dict(lines.op10_line_dedup(spark, sf).dtypes)["n_dropped"] == "bigint"
    assert dict(packing.op8_best_fit_packing(spark, sf).dtypes) == {"doc_id": "bigint", "piece": "int", "start": "bigint", "length": "bigint", "ids_crc32": "bigint", "sequence_id": "bigint", "offset": "bigint"}
    assert spark.range(1).select(F.lit(1)).count() == 1
