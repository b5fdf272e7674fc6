"""Operators against brute force on small inputs, and their edge cases."""

import collections
import hashlib
import math
import random
import re
import zlib

import numpy as np
import pytest

from nzspan.llm import coder, common, edit_counts, hidden_markov, mixing, pieces, simhash, spots, suffixes, token_files, topk, toxicity

WORDS = "the of and alpha beta gamma delta epsilon zeta eta theta iota kappa lambda mu nu".split()


def prose(rng, n):
    return " ".join(rng.choice(WORDS) + str(rng.randint(0, 40)) for _ in range(n))


@pytest.fixture(scope="module")
def rows():
    """Ids and texts with nulls, empty and very long texts, ties, copies, near copies and repeated rows."""
    rng = random.Random(1)
    texts = [prose(rng, rng.randint(1, 120)) for _ in range(40)]
    shared = prose(rng, 90)
    near = texts[3].split(" ")
    near[len(near) // 2] = "changed"
    texts += [None, "", "   ", "\n", "é", "日本語テキスト", "a" * 3000, "ab" * 700, texts[0], texts[0], " ".join(near), shared + " tail", "head " + shared, prose(rng, 9000), shared + " " + shared]
    out = list(enumerate(texts))
    return [*out, out[5], (None, texts[7]), (None, None)]


@pytest.fixture(scope="module")
def documents(spark, rows):
    data = [(i, t, "en", None if (i or 0) % 7 == 3 else f"s{(i or 0) % 4}", len(t or "")) for i, t in rows]
    return spark.createDataFrame(data, "doc_id long, text string, lang string, source string, n_chars long").repartition(3).cache()


@pytest.fixture(scope="module")
def empty(documents):
    return documents.where("false")


def test_words_agree():
    for text in ("A b c\x1cd", "x\x0by\x0cz", " lead", "É Å", ""):
        words = re.findall(common.WORD, text)
        assert common.words_of(text) == words
        assert common.byte_words(text) == [w.translate(common.TO_LOWER).encode() for w in words]


# --- mixing


def test_mix(spark, documents, rows, empty):
    for _ in range(2):
        mixed = mixing.mix(documents, fanout=4).orderBy("doc_id", "size").collect()
        again = [tuple(r) for r in mixed]
        if _:
            assert again == before
        before = again
    assert len(mixed) == len(rows)
    sizes = collections.Counter()
    taken = collections.Counter()
    target = {}
    largest = collections.Counter()
    for r in mixed:
        assert 0 <= r["taken"] <= 3 * r["size"] and r["taken"] == r["copies"] * r["size"]
        sizes[r["source"]] += r["size"]
        taken[r["source"]] += r["taken"]
        target[r["source"]] = r["target"]
        largest[r["source"]] = max(largest[r["source"]], r["size"])
    names = sorted(sizes, key=lambda s: (s is None, s or ""))
    weight = {s: i % 3 + 1 for i, s in enumerate(names)}
    capped, total = {}, sum(sizes.values())
    while True:  # share, hold at the cap, share what is left
        free = [s for s in names if s not in capped]
        left = total - sum(capped.values())
        share = {s: left * weight[s] / sum(weight[f] for f in free) for s in free}
        over = [s for s in free if share[s] > 3 * sizes[s]]
        if not over:
            break
        capped |= {s: 3 * sizes[s] for s in over}
    for s in names:
        assert math.isclose(target[s], (capped | share)[s], rel_tol=1e-9)
        assert abs(taken[s] - target[s]) <= largest[s] + 1e-6
    assert mixing.mix(empty).count() == 0


def test_pivot_keeps_mass_and_chances():
    rng = np.random.default_rng(0)
    for _ in range(50):
        n = rng.integers(1, 30)
        size, share = rng.integers(1, 50, n).astype(float), rng.random(n)
        out = mixing.pivot(size, share, rng.random(n))
        assert np.isclose((size * out).sum(), (size * share).sum()) and ((out > 0) & (out < 1)).sum() <= 1
        assert out.min() >= 0 and out.max() <= 1
    kept = np.mean([mixing.pivot(np.array([3.0, 5.0, 2.0]), np.array([0.3, 0.6, 0.5]), rng.random(3)) for _ in range(4000)], axis=0)
    assert np.allclose(kept, [0.3, 0.6, 0.5], atol=0.03)


# --- near-duplicates


def test_simhash(documents, rows, empty):
    import xxhash

    def brute(text):
        words = re.findall(common.WORD, (text or "").translate(common.TO_LOWER))
        if not words:
            return 0
        shingles = [" ".join(words[i : i + 4]) for i in range(max(1, len(words) - 3))]
        hashes = [xxhash.xxh64_intdigest(s.encode(), seed=42) for s in shingles]
        return sum(1 << b for b in range(64) if 2 * sum(h >> b & 1 for h in hashes) > len(hashes))

    prints = {t: brute(t) for _, t in rows}
    assert all(simhash.fingerprint(t) == p for t, p in prints.items())
    ids = [i for i, _ in rows if i is not None]
    forest = simhash.Forest(len(rows))
    for a in range(len(rows)):
        for b in range(a):
            if bin(prints[rows[a][1]] ^ prints[rows[b][1]]).count("1") <= 4:
                forest.join(a, b)
    expected = collections.defaultdict(set)
    for a, (i, _) in enumerate(rows):
        expected[i].add(min((j for b, (j, _) in enumerate(rows) if j is not None and forest.root(b) == forest.root(a)), default=None))
    for block in (2048, 3):
        found = simhash.near_duplicates(documents, block=block).collect()
        assert len(found) == len(rows) and len(ids) == len([r for r in found if r["doc_id"] is not None])
        for r in found:
            assert r["component_id"] in expected[r["doc_id"]]
    assert simhash.near_duplicates(empty).count() == 0


def test_grid_has_all_links_within_the_radius():
    rng = np.random.default_rng(4)
    fp = rng.integers(0, 1 << 63, 300).astype(np.uint64)
    near = fp.copy()
    for k in range(len(fp)):
        for bit in rng.choice(64, 4, replace=False):
            near[k] ^= np.uint64(1) << np.uint64(bit)
    masks = np.array(simhash.cell_masks(), np.int64).view(np.uint64)
    low = np.uint64(0x5555555555555555)

    def counts(x):
        a, b = x & low, (x >> np.uint64(1)) & low
        return ((a & b) << np.uint64(1)) | (a ^ b)

    assert ((counts(fp)[:, None] & masks) == (counts(near)[:, None] & masks)).any(axis=1).all()
    assert (simhash.segment_distance(fp, near) <= simhash.hamming(fp, near)).all()


# --- suffixes


@pytest.mark.parametrize(("length", "gram", "crowd"), [(400, 128, 4096), (60, 16, 3)])
def test_repeats(documents, rows, empty, length, gram, crowd):
    data = [(t or "").encode() for _, t in rows]
    seen = collections.Counter(d[k : k + length] for d in data for k in range(len(d) - length + 1))
    expected = collections.Counter()
    for (i, _), d in zip(rows, data, strict=True):
        spans = [(k, k + length) for k in range(len(d) - length + 1) if seen[d[k : k + length]] > 1]
        kept, runs = suffixes.without(d, spans)
        expected[(i, len(d), len(d) - len(kept), len(runs), hashlib.sha256(kept).hexdigest())] += 1
    found = suffixes.remove_repeats(documents, length, gram, crowd).collect()
    assert collections.Counter((r["doc_id"], r["n_bytes"], r["n_removed"], r["n_spans"], r["kept_sha256"]) for r in found) == expected
    assert suffixes.remove_repeats(empty).count() == 0


def test_repeats_as_the_query_cuts_them(spark):
    rng = np.random.default_rng(8)
    letters = np.frombuffer(b"abcdefghijklmnopqrstuvwxyz", np.uint8)
    words = lambda n: " ".join(rng.choice(letters, rng.integers(2, 10)).tobytes().decode() for _ in range(n))
    long, short, few = words(90)[:400], words(90)[:399], " ".join("abcde"[: 1 + i % 5] for i in range(52))
    texts = []
    for planted in (long, short, few):
        for edge in ("[", "]"):  # so that no copy goes on beyond the passage
            texts.append(words(200) + edge + planted + edge + words(200))
    texts += [words(400), "", words(30)]
    df = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    found = {r["doc_id"]: (r["n_removed"], r["n_spans"]) for r in suffixes.remove_repeats(df).collect()}
    assert found == {i: (400, 1) if i < 2 else (0, 0) for i in range(len(texts))}


def test_multikey_order():
    rng = np.random.default_rng(5)
    rows = rng.integers(0, 2, (200, 24)).astype(np.uint8)
    rows[50:60] = rows[0]
    order, same = suffixes.multikey_order(rows.view(">u8").astype(np.uint64).reshape(200, -1))
    values = [rows[i].tobytes() for i in order]
    assert values == sorted(values)
    for a, b, n in zip(values, values[1:], same[1:], strict=False):
        assert n == next((k for k in range(24) if a[k] != b[k]), 24)


# --- encoding


def chunked(model, text, chunk):
    normal = model.normalize(text)
    parts = list(pieces._cut(normal, chunk, model.longest))
    matrices = [[(s + o, e + o, t + o, f + o, w) for s, e, t, f, w in model.transfer(x, a, b, k == 0, last)] for k, last, o, a, b, x in parts]
    states = pieces.combine(matrices)
    return [i for (k, last, o, a, b, x), (u, v) in zip(parts, states, strict=True) for i in model.backtrace(x, a, b, (u[0] - o, u[1] - o), (v[0] - o, v[1] - o), last)]


def test_chunks_encode_as_the_library():
    with open(pieces.default_model(), "rb") as file:
        proto = file.read()
    model, rng = pieces.Pieces(proto), random.Random(6)
    parts = ["the", "and", "ing", "a", "é", "ß", " ", "  ", "\n", "日", "🙂", "tion", "1", "23"]
    for k in range(120):
        text = "".join(rng.choice(parts if k % 2 else parts[:6] + parts[11:]) for _ in range(rng.randint(1, 60)))
        for chunk in (5, 17):
            assert chunked(model, text, chunk) == model.library.encode(text)


def test_pieces(spark, documents, rows, empty):
    import sentencepiece

    library = sentencepiece.SentencePieceProcessor(model_file=pieces.default_model())
    expected = collections.Counter((i, tuple(library.encode(t or ""))) for i, t in rows)
    clash = documents.withColumn("ids", documents["lang"]).withColumn("decoded", documents["lang"])
    for chunk in (pieces.CHUNK, 500):
        encoded = pieces.encode_documents(clash.select("doc_id", "text", "ids"), chunk=chunk)
        assert collections.Counter((r["doc_id"], tuple(r["ids"])) for r in encoded.collect()) == expected
    assert all(r["decoded"] == (r["text"] or "") for r in pieces.decode_documents(encoded).collect())
    assert pieces.encode_documents(empty).count() == 0


@pytest.mark.parametrize("n", [0, 1, 2, 63, 64, 65, 1000])
def test_coder_round_trip(n):
    rng = np.random.default_rng(n)
    for ids in (rng.integers(0, 1 << 32, n), np.zeros(n), np.full(n, (1 << 32) - 1), rng.zipf(1.4, n) % 50000, np.arange(n) % 7):
        ids = ids.astype(np.uint32)
        payload = coder.encode_block(ids, lane=64)
        assert (coder.decode_block(payload) == ids).all()
    for k in (0, len(payload) // 2, len(payload) - 1):
        broken = bytearray(payload)
        broken[k] ^= 1
        with pytest.raises(coder.Damaged):
            coder.decode_block(bytes(broken))


def test_mixture_of_three_orders():
    rng = np.random.default_rng(3)
    model = coder.Predictor(50)
    for _ in range(60):
        model.look(50)
        below = np.stack([model.mixture(np.full(50, k)) for k in range(coder.CLASSES + 1)])
        assert (below[0] == 0).all() and (below[-1] == 1 << coder.SCALE).all() and (np.diff(below, axis=0) >= 1).all()
        symbol = rng.integers(0, 6, 50)
        for target in (model.mixture(symbol), model.mixture(symbol + 1) - 1):
            found, low, high = model.find(target)
            assert (found == symbol).all() and (low <= target).all() and (target < high).all()
        assert (model.weights.sum(axis=0) == 1 << coder.WEIGHT).all() and (model.weights > 0).all()
        rank = rng.integers(0, 30, 50)
        model.learn(rank, coder.bit_length(rank), symbol)


def test_higher_orders_pay():
    rng = np.random.default_rng(4)
    follow = rng.integers(0, 60, (60, 60))
    ids = [1, 2]
    for _ in range(60_000):
        ids.append(int(follow[ids[-2], ids[-1]]) if rng.random() < 0.9 else int(rng.integers(0, 60)))
    chained, shuffled = np.array(ids), rng.permutation(ids)
    assert len(coder.encode_block(chained, 128)) < 0.5 * len(coder.encode_block(shuffled, 128))


def test_token_files(spark, documents, rows, empty, tmp_path):
    from tokenizers import Tokenizer

    library = Tokenizer.from_file(token_files.default_tokenizer())
    token_files.write_token_files(documents, f"{tmp_path}/ids", block=700)
    found = token_files.read_token_files(spark, f"{tmp_path}/ids").collect()
    start, expected = 0, collections.Counter()
    for i, t in sorted(rows, key=lambda r: (r[0] is not None, r[0] or 0, r[1] is not None, r[1] or "")):
        ids = [*library.encode(t or "", add_special_tokens=False).ids, 0]
        expected[(i, start, tuple(ids))] += 1
        start += len(ids)
    assert collections.Counter((r["doc_id"], r["start"], tuple(r["ids"])) for r in found) == expected
    token_files.write_token_files(empty, f"{tmp_path}/none")
    assert token_files.read_token_files(spark, f"{tmp_path}/none").count() == 0


def test_coder_takes_few_steps(monkeypatch):
    ids = (np.random.default_rng(5).zipf(1.3, 40_000) % 5000).astype(np.uint32)
    looks, look = [], coder.Predictor.look
    monkeypatch.setattr(coder.Predictor, "look", lambda self, n: (looks.append(n), look(self, n))[1])
    payload = coder.encode_block(ids)
    assert (coder.decode_block(payload) == ids).all()
    # long arrays: a step takes an id of every lane, and lanes are short
    assert len(looks) <= 2 * 256 and sum(looks) == 2 * len(ids)


@pytest.mark.parametrize("lane", [1, 3, 1000])
def test_coder_with_any_lanes(lane):
    rng = np.random.default_rng(lane)
    for ids in (rng.integers(0, 1 << 32, 66_000 if lane == 1 else 4000), rng.zipf(1.2, 4000) % (1 << 24)):
        ids = ids.astype(np.uint32)
        payload = coder.encode_block(ids, lane)
        assert (coder.decode_block(payload) == ids).all()
        short = payload[:-6]
        with pytest.raises(coder.Damaged):
            coder.decode_block(short + zlib.crc32(short).to_bytes(4, "little"))


def test_new_words_go_to_the_library_together(monkeypatch):
    with open(token_files.default_tokenizer(), encoding="utf-8") as file:
        settings = file.read()
    encoder = token_files.encoder_of(settings)
    assert token_files.encoder_of(settings) is encoder  # words stay from task to task
    rng = random.Random(8)
    parts = ["the", "Alpha", "é", "日本", "x\ny", "\n", "\t", "\u00a0", "\x1c", "\u2003", "  ", "", "<|endoftext|>", "a<|endoftext|>", "\u0120", "\u0120b", "'s", "12", "...", "\x00"]
    texts = ["", " ", "a", " a", "a ", "a  b", "\n a", "a \n", "  "] + [" ".join(rng.choice(parts) for _ in range(rng.randint(1, 30))) for _ in range(300)] + ["".join(rng.choice(parts) for _ in range(9)) for _ in range(100)]
    plain = [" ".join(f"w{i}q{j}" for j in range(200)) for i in range(20)]
    library, given = encoder.library, []

    class Counted:
        def encode_batch_fast(self, some, **more):
            given.extend(some)
            return library.encode_batch_fast(some, **more)

    for memory in (token_files.MEMORY, 0):
        monkeypatch.setattr(token_files, "MEMORY", memory)
        encoder.forget()
        for some in (texts, texts[:40], [], plain):
            found = encoder.encode_batch(some)
            assert [f.tolist() for f in found] == [library.encode(t, add_special_tokens=False).ids for t in some]
    monkeypatch.setattr(encoder, "library", Counted())
    encoder.forget()
    encoder.encode_batch(plain)
    assert len(given) <= 20 + -(-20 * 199 // token_files.TOGETHER)
    assert [list(token_files._slices(t)) for t in ([], ["a"], ["ab", "c"])] == [[], [(0, 1)], [(0, 2)]]


def test_edit_counts(documents, rows, empty):
    path, pattern = edit_counts.default_ranks()
    with open(path, "rb") as file:
        counter = edit_counts.Counter(file.read(), pattern)
    rng = random.Random(7)
    parts = ["the", "foo", " ", "  ", "\n", "'s", "'ll", "'", "12", "é", "日", ".", "!!", " a"]
    for _ in range(60):
        text = "".join(rng.choice(parts) for _ in range(rng.randint(0, 900)))
        tree = edit_counts.Tree(*counter.leaves(text))
        for _ in range(5):
            more = "".join(rng.choice(parts) for _ in range(rng.choice([0, 1, 4, 600])))
            text, _n = edit_counts.edit(counter, tree, text, rng.randint(0, len(text) + 2), rng.choice([0, 1, 5, 400]), more)
            assert (tree.n_tokens, tree.n_chars) == (len(counter.library.encode_ordinary(text)), len(text))
    counted = edit_counts.count_documents(documents.select("doc_id", "text"))
    for r in counted.collect():
        assert r["n_tokens"] == sum(r["leaf_tokens"]) == len(counter.library.encode_ordinary(r["text"] or ""))
    assert edit_counts.count_documents(empty).count() == 0


def test_op3_counts_what_the_edits_leave(spark):
    data = "/root/testdata/sf0.001"
    path, pattern = edit_counts.default_ranks()
    with open(path, "rb") as file:
        library = edit_counts.Counter(file.read(), pattern).library
    texts = {r["doc_id"]: r["text"] or "" for r in spark.read.parquet(f"{data}/documents.parquet").collect()}
    got = edit_counts.op3_edit_counts(spark, data).collect()
    assert {r["doc_id"] for r in got} == set(texts)
    for r in got:
        text = texts[r["doc_id"]]
        n = len(text)
        at, head = 2 * n // 3, text[:24]
        edited = text[:at] + head + text[at + 16 :]
        edited = edited[: n // 3] + " edited" + edited[n // 3 :]
        edited = edited[: max(0, len(edited) - 8)]
        assert (r["n_tokens"], r["edited_tokens"], r["edited_chars"]) == (len(library.encode_ordinary(text)), len(library.encode_ordinary(edited)), len(edited))
        assert r["n_encoded"] <= 3 * (n + 31)  # no edit encodes more than the text of its time


# --- fingerprints


def test_spots(spark, documents, rows, empty):
    docs = documents.select("doc_id", "text", "lang")
    df = spots.with_next(spots.with_sketch(docs, "text", "size", "sketch"), "doc_id", ["text"], rows_per_range=4).collect()
    order = sorted(rows, key=lambda r: (r[0] is None, -(r[0] or 0), r[1] is not None, r[1] or ""))
    follows = collections.Counter((i, t, order[(k + 1) % len(order)][1]) for k, (i, t) in enumerate(order))
    assert collections.Counter((r["doc_id"], r["text"], r["next_text"]) for r in df) == follows
    by_text = {}
    for r in df:
        assert by_text.setdefault(r["text"], r["sketch"]) == r["sketch"]
    assert spots.with_next(empty, "doc_id", ["text"]).count() == 0


def test_op6_against_plain_sets(spark):
    data = "/root/testdata/sf0.001"

    def signatures(text):
        words = [w for w in re.split("[\\x20\\x09-\\x0D]+", text.lower()) if w]
        starts = [k for k, w in enumerate(words) if w in set(spots.ANCHORS)]
        content = [words[a + 1 : b] for a, b in zip(starts, [*starts[1:], len(words)], strict=False)]
        found = set()
        for k, a in enumerate(starts):
            chain = [words[a], *[w for c in content[k : k + spots.CHAIN + 2] for w in c]]
            found.add(tuple(chain[: spots.CHAIN + 1]))
        return found or set(words)

    def alike(a, b):
        return len(a & b) / len(a | b) if a | b else 1.0

    texts = {r["doc_id"]: r["text"] or "" for r in spark.read.parquet(f"{data}/documents.parquet").collect()}
    down = sorted(texts, reverse=True)
    follows = dict(zip(down, [*down[1:], down[0]], strict=True))
    got = spots.op6_spots(spark, data).collect()
    assert {r["doc_id"] for r in got} == set(texts)
    for r in got:
        text, after = texts[r["doc_id"]], texts[follows[r["doc_id"]]]
        half = len(text) // 2
        edited = text[: len(text) - half] + after[:half]
        assert r["n_chars"] == len(text) and r["edited_sha256"] == hashlib.sha256(edited.encode()).hexdigest()
        own = signatures(text)
        assert r["near_edited"] == pytest.approx(alike(own, signatures(edited))) and r["near_next"] == pytest.approx(alike(own, signatures(after)))
        assert int(r["fingerprint"][:8], 16) == len(own)


def test_spots_compares_whole_sets(spark, tmp_path):
    rng = random.Random(14)
    texts = [" ".join(f"the a{rng.randint(0, 40)} b{rng.randint(0, 8)}" for _ in range(n)) for n in (400, 300, 3, 0)]
    spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string").write.parquet(f"{tmp_path}/documents.parquet")

    def chains(text):
        words = text.split()
        return {tuple(words[k : k + 3]) for k in range(0, len(words), 3)}

    found = {r["doc_id"]: r for r in spots.op6_spots(spark, str(tmp_path)).collect()}
    for k, text in enumerate(texts):
        ours, after = chains(text), chains(texts[(k - 1) % len(texts)])  # rows follow in descending order
        assert found[k]["near_next"] == pytest.approx(len(ours & after) / len(ours | after))
        assert len(found[k]["fingerprint"]) == 8 * (1 + len(ours))


def test_spot_links(spark):
    rng = random.Random(8)
    base = " ".join(f"the {rng.choice(WORDS)}{rng.randint(0, 999)} x{rng.randint(0, 999)}" for _ in range(60))
    near = base.replace("x", "x", 1) + " the final words"
    other = " ".join(f"of {rng.choice(WORDS)}{rng.randint(0, 999)} y{rng.randint(0, 999)}" for _ in range(60))
    df = spark.createDataFrame([(1, base), (2, near), (3, other), (4, base), (5, None), (6, "")], "doc_id long, text string")
    membership, links = spots.spot_links(df)
    sets = {r["doc_id"]: r["set_id"] for r in membership.collect()}
    assert sets[1] == sets[4] and sets[5] == sets[6]
    assert {frozenset((r["a"], r["b"])) for r in links.collect()} == {frozenset((sets[1], sets[2]))}


# --- search


def test_topk(spark):
    rng = np.random.default_rng(9)
    data = [(i, rng.integers(-3, 4, 6).tolist()) for i in range(150)] + [(7, [3] * 6), (200, [0] * 6), (None, [1] * 6), (300, [1, 2])]
    df = spark.createDataFrame(data, "vec_id long, v array<long>")
    asked = df.where("vec_id % 20 = 0")
    found = collections.defaultdict(list)
    for r in topk.top_inner_products(df, asked, 5, rows=40, per_block=3).orderBy("query_id", "rank").collect():
        found[r["query_id"]].append((r["score"], r["vec_id"]))
    for q, v in data:
        if q is not None and q % 20 == 0:
            scores = sorted(((sum(a * b for a, b in zip(v, w, strict=True)), i) for i, w in data if i is not None and i != q and len(w) == len(v)), key=lambda x: (-x[0], x[1]))
            assert found[q] == scores[:5]
    nan = float("nan")
    odd = spark.createDataFrame([(1, [1.0, None]), (2, None), (3, [nan, 1.0]), (4, [float("inf"), 0.0]), (5, [0.5, -0.5])], "vec_id long, embedding array<float>")
    assert [tuple(r) for r in topk.integer_vectors(odd).collect()] == [(5, [512, -512])]
    assert topk.top_inner_products(df.where("false"), asked).count() == 0


def test_threshold_stops_early():
    rng = np.random.default_rng(10)
    vectors = rng.integers(-5, 6, (2000, 3))
    vectors[17] = [90, 90, 90]
    top, scored = topk.threshold_top(vectors, np.arange(2000), np.array([2, 3, 1]), -1, 1)
    assert top == [(540, 17)] and scored < 500


# --- language model


def test_markov_recursions_against_plain_sums():
    rng = np.random.default_rng(4)
    chain = hidden_markov.Chain.random(np.full(9, 1 / 9), 4)
    texts = [rng.integers(0, 9, n) for n in (1, 2, 7, 40, 40, 133)]
    start, move, emit, told = np.zeros(4), np.zeros((4, 4)), np.zeros((9, 4)), []
    for text in texts:
        ahead, back = [chain.start * chain.emit[text[0]]], [np.ones(4)]
        for c in text[1:]:
            ahead.append(ahead[-1] @ chain.move * chain.emit[c])
        for c in text[:0:-1]:
            back.insert(0, chain.move @ (chain.emit[c] * back[0]))
        whole = ahead[-1].sum()
        told.append(np.log10(whole))
        start += ahead[0] * back[0] / whole
        for t, c in enumerate(text):
            emit[c] += ahead[t] * back[t] / whole
            if t:
                move += chain.move * np.outer(ahead[t - 1], chain.emit[c] * back[t]) / whole
    assert np.allclose(chain.likelihood(texts), told, rtol=1e-9)
    sums = np.zeros(4), np.zeros((4, 4)), np.zeros((9, 4))
    assert np.isclose(chain.expect(texts, *sums), sum(told), rtol=1e-5)
    for ours, plain in zip(sums, (start, move, emit), strict=True):
        assert np.allclose(ours, plain, rtol=1e-3)


def test_markov_index_tells_unknown_words():
    words = [hidden_markov.END, b"a", b"bb"]
    v = hidden_markov.Vocabulary(words, np.array([2, 5, 1]), 8, 3, np.full(hidden_markov.SUFFIXES, 0.5))
    assert list(map(v.index.__getitem__, [b"bb", b"c", hidden_markov.END])) == [2, -1, 0] and len(v.index) == 3
    classes, rare, _, _ = v.read("A c c bb")
    assert classes.tolist() == [1, *[hidden_markov.OWN + hidden_markov.suffix_class(b"c")] * 2, 2, 0] and rare == {b"c": 2}


def test_markov(documents, rows, empty):
    rng = np.random.default_rng(11)
    chain = hidden_markov.Chain.random(np.full(5, 0.2), 3)
    texts = [rng.integers(0, 5, n) for n in (1, 4, 2, 7)]

    def alone(x):
        state = chain.start * chain.emit[x[0]]
        for o in x[1:]:
            state = (state @ chain.move) * chain.emit[o]
        return math.log10(state.sum())

    assert np.allclose(chain.likelihood(texts), [alone(x) for x in texts])
    start, move, emit = np.zeros(3), np.zeros((3, 3)), np.zeros((5, 3))
    chain.expect(texts, start, move, emit)
    assert np.isclose(start.sum(), 4) and np.isclose(move.sum(), 10) and np.isclose(emit.sum(), 14)
    better = hidden_markov.Chain(start / start.sum(), move / move.sum(1, keepdims=True), emit / emit.sum(0))
    assert better.likelihood(texts).sum() >= chain.likelihood(texts).sum()

    held = lambda i: i is not None and zlib.crc32(str(i).encode()) % 5 == 1
    tokens = {(i, t): [*common.byte_words(t), b"\n"] for i, t in rows}
    counts = collections.Counter(w for i, t in rows if not held(i) for w in tokens[(i, t)])
    total, mass = sum(counts.values()), sum(counts.values()) + 0.5 * (len(counts) + 1)
    from pyspark.sql import functions as F

    scored = hidden_markov.score_documents(documents, F.coalesce(common.fold_bucket(F.col("doc_id")) == 1, F.lit(False)), states=3, passes=1)
    expected = collections.Counter((i, len(tokens[(i, t)]), sum(counts[w] > 0 for w in tokens[(i, t)]), round(sum(math.log10((counts[w] + 0.5) / mass) for w in tokens[(i, t)]), 5)) for i, t in rows)
    found = scored.collect()
    assert collections.Counter((r["doc_id"], r["n_tokens"], r["n_known"], round(r["base_score"], 5)) for r in found) == expected
    assert all(r["train_tokens"] == total and r["score"] < 0 and math.isfinite(r["score"]) for r in found)
    assert hidden_markov.score_documents(empty, F.lit(False), states=2, passes=1).count() == 0


def test_markov_learns_from_the_end_of_long_texts(spark):
    # all texts start alike for 3,000 tokens; only what follows tells that c comes after b
    texts = [" ".join(["a"] * 3000 + ["b", "c"] * 400) for _ in range(6)]
    df = spark.createDataFrame([(k, t) for k, t in enumerate(texts)], "doc_id long, text string").repartition(3)
    v = hidden_markov.vocabulary(hidden_markov.count_words(df))
    chain = hidden_markov.train(df, v, states=3)
    whole = chain.likelihood([v.read(t)[0] for t in texts]).sum()
    share = hidden_markov.class_shares(v)
    alone = hidden_markov.Chain.random(share, 3)
    seen = [v.read(t)[0] for t in texts]
    before = -math.inf
    while True:  # the same passes in one process
        sums = np.zeros(3), np.zeros((3, 3)), np.zeros((len(share), 3))
        told = alone.expect(seen, *sums)
        assert told == pytest.approx(alone.likelihood(seen).sum())
        alone = hidden_markov.Chain.from_counts(*sums, share)
        if told - before <= hidden_markov.TOLERANCE * abs(told):
            break
        before = told
    assert whole == pytest.approx(alone.likelihood(seen).sum(), rel=1e-6)


# --- toxicity


def test_toxicity(spark, documents, empty):
    rng = random.Random(12)
    bad = ["vilified", "wretchedly", "despicable"]

    def text(toxic):
        words = prose(rng, 60).split(" ")
        for _ in range(4 if toxic else 0):
            words.insert(rng.randint(0, 60), rng.choice(bad))
        return " ".join(words)

    model = toxicity.fit([text(True) for _ in range(60)], [text(False) for _ in range(200)])
    data = [(k, text(k % 2 == 1)) for k in range(60)] + [(100, None), (101, "")]
    scored = toxicity.score_documents(spark.createDataFrame(data, "doc_id long, text string"), model).collect()
    right = [(r["predicted"] == 1) == (r["doc_id"] % 2 == 1) for r in scored if r["doc_id"] < 100]
    assert sum(right) >= 57 and all(0 <= r["score"] <= 1 for r in scored)
    assert len({r["score"] for r in scored if r["doc_id"] >= 100}) == 1
    none = toxicity.fit([], [])
    assert toxicity.score_documents(documents, none).where("predicted = 1").count() == 0
    assert toxicity.score_documents(empty, none).count() == 0


def test_dictionaries_are_narrowed_to_toxic_windows():
    rng = random.Random(15)
    # each of these words is in few toxic texts, far fewer than the one that is in all
    bad = [f"vile{k}monger" for k in range(6)]
    toxic = [prose(rng, 60) + " despicable " + bad[k % 6] + " " + prose(rng, 5) for k in range(240)]
    model = toxicity.fit(toxic, [prose(rng, 60) for _ in range(400)])
    assert b"despicable" in model.toxic and b"despicable" not in model.ordinary
    differ = model.differ()
    telling = differ([[f" {w} ".encode() for w in [*bad, "despicable"]]])[0]
    assert telling.min() > np.percentile(differ([toxicity.windows_of(prose(rng, 2000))])[0], 99)


def test_toxicity_in_each_language():
    rng = random.Random(17)
    syllables = {"one": "ka lo mi ru te sa po ne".split(), "two": "ößch ung keit äz eur über ein ll".split()}
    bad = {"one": ["scoundrel", "brutish"], "two": ["drüwix", "gemäfft"]}

    def text(kind, is_toxic):
        words = ["".join(rng.choice(syllables[kind]) for _ in range(rng.randint(1, 4))) for _ in range(80)]
        for _ in range(3 if is_toxic else 0):
            words.insert(rng.randint(0, len(words)), rng.choice(bad[kind]) + rng.choice(["", ".", ","]))
        return " ".join(words)

    kinds = ["one", "one", "one", "two"]
    model = toxicity.fit([text(kinds[k % 4], True) for k in range(160)], [text(kinds[k % 4], False) for k in range(320)])
    differ = model.differ()
    for kind in ("one", "two"):
        for is_toxic in (True, False):
            texts = [toxicity.windows_of(text(kind, is_toxic)) for _ in range(50)]
            scores = model.score(np.array([toxicity.features(d) for d in differ(texts)]))
            assert np.mean((scores >= 0.5) == is_toxic) >= 0.9, (kind, is_toxic)


def test_windows_and_lengths_one_at_a_time():
    import zstandard

    text = "Short Words and " + "y" * 130 + " ünd " + "x" * 48 + "\n end"
    windows = toxicity.windows_of(text)
    assert b"".join(w.strip() for w in windows) == b"".join(common.byte_words(text)) and max(map(len, windows)) <= toxicity.WIDE + 2
    content = b" despicable  wretched  some ordinary words stand here too "
    p = zstandard.ZstdCompressionParameters.from_level(3, min_match=3, write_content_size=False, write_checksum=False, write_dict_id=False)
    dictionary = zstandard.ZstdCompressionDict(content + toxicity.FRAME, dict_type=zstandard.DICT_TYPE_RAWCONTENT)
    alone = [len(zstandard.ZstdCompressor(dict_data=dictionary, compression_params=p).compress(toxicity.FRAME + w + toxicity.FRAME)) for w in windows]
    assert toxicity.compressed_lengths(content)(windows).tolist() == alone
    assert toxicity.windows_of(None) == toxicity.windows_of(" \t") == []
    assert toxicity.features(np.zeros(0, np.int64))[1:].tolist() == [0.0] * (1 + len(toxicity.THRESHOLDS))


def test_op7_scores_as_one_process_does(spark):
    data = "/root/testdata/sf0.001"
    docs = {r["doc_id"]: r["text"] for r in spark.read.parquet(f"{data}/documents.parquet").collect()}
    labels = {r["doc_id"]: r["toxic"] for r in spark.read.parquet(f"{data}/labels.parquet").collect()}
    fold = lambda i: zlib.crc32(str(i).encode()) % 5
    sample = toxicity.training_sample(spark.read.parquet(f"{data}/documents.parquet"), spark.read.parquet(f"{data}/labels.parquet"))
    for value, texts in zip((1, 0), sample, strict=True):
        assert sorted(texts) == sorted(docs[i] for i, v in labels.items() if v == value and fold(i) != 0)
    model = toxicity.fit(*sample)
    got = toxicity.op7_toxicity(spark, data).collect()
    assert {r["doc_id"] for r in got} == set(docs)
    for r in got:
        want = float(model.score(toxicity.features(model.differ()([toxicity.windows_of(docs[r["doc_id"]])])[0])[None, :])[0])
        assert r["score"] == pytest.approx(want) and r["predicted"] == int(want >= 0.5) and r["held_out"] == (fold(r["doc_id"]) == 0)


def test_training_samples_cover_whole_texts():
    rng = random.Random(16)
    texts = [toxicity.windows_of(prose(rng, 1500) + " the same rare closing") for _ in range(6)]
    assert sum(b"rare closing" in x for x in toxicity.pieces(texts)) >= 3
    assert b"".join(toxicity.pieces(texts)).split() == [w.strip() for t in texts for w in t]


def test_components_keep_the_last_turn_only(spark):
    import os
    import random

    from nzspan.llm.components import connected_components
    from nzspan.session import shared_folder

    where = shared_folder(spark).removeprefix("file:")
    ids = list(range(300))
    random.Random(5).shuffle(ids)
    before = set(os.listdir(where))
    labels = connected_components(spark.createDataFrame(list(zip(ids[:-1], ids[1:], strict=True)), "a long, b long"))
    assert {r["component"] for r in labels.collect()} == {0} and labels.count() == 300
    assert len(set(os.listdir(where)) - before) == 1


def test_cells_do_not_pass_the_driver(spark):
    from nzspan.llm import simhash
    from nzspan.session import written

    prints = written(spark.range(500).selectExpr("id AS node", "xxhash64(id) AS fp"), "prints")
    plan = simhash.fingerprint_links(prints)._jdf.queryExecution().executedPlan().toString()
    assert "Broadcast" not in plan and "SortMergeJoin" in plan


def test_components_end_at_stars(spark, monkeypatch):
    from nzspan.llm import components

    turns, write = [], components.written
    monkeypatch.setattr(components, "written", lambda df, name: turns.append(name) or write(df, name))
    stars = [(k, 100 + 10 * k + j) for k in range(5) for j in range(8)]
    labels = components.connected_components(spark.createDataFrame(stars, "a long, b long"))
    assert {(r["node"], r["component"]) for r in labels.collect()} == {(b, a) for a, b in stars} | {(a, a) for a, _ in stars}
    assert len(turns) == 1  # edges that are stars already need no turn
    assert components.connected_components(spark.createDataFrame([(3, 3)], "a long, b long")).count() == 0


def test_frequent_shingles_are_chosen_where_they_lie(spark):
    from nzspan.llm import shingles

    texts = ["a b c"] * 2 + ["a b c d"] * 4 + ["a b c d e"] * 2 + ["x y z w"] * 3 + ["once only here"]
    df = spark.createDataFrame([(k, t) for k, t in enumerate(texts)], "doc_id long, text string")
    counts = {"a b c": 8, "b c d": 6, "x y z": 3, "y z w": 3}  # the others are in two texts at most
    by_hash = {int(shingles.shingle_hashes(w, 3)[0]): n for w, n in counts.items()}
    for most, expected in ((1, 1), (2, 2), (3, 2), (4, 4), (100, 4), (0, 0)):  # of equal counts all are taken or none
        s, n = shingles.frequent_shingles(df, shingle=3, one_in=1, most=most)
        assert list(s) == sorted(s) and len(s) == expected
        assert dict(zip(s.tolist(), n.tolist(), strict=True)).items() <= by_hash.items()


def test_driver_gives_back_what_it_freed(spark, monkeypatch):
    import corpus_pipeline
    from nzspan import session

    assert session.trim(spark)
    given = []
    monkeypatch.setattr(common, "give_back", lambda: given.append(1))
    data = "/root/testdata/sf0.001"
    corpus_pipeline.toxicity_stage(spark, spark.read.parquet(f"{data}/documents.parquet"), data)
    assert given  # after fitting, on the driver
