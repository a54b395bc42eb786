"""Operators against brute force, the libraries they must agree with, and odd rows."""

import hashlib
import math
import random
import zlib
from collections import Counter
from itertools import combinations

import numpy as np
import public_tokenizers as P
import pyarrow as pa
import pytest
import tiktoken
from pyspark.sql import functions as F
from tokenizers import Tokenizer
from xxhash import xxh64_intdigest

from skewgraph.llm import bpe, brown, chat, hamming, html_wrappers, lines, packing, quality, sharding, simhash, topk
from skewgraph.llm import queries as llm_queries
from skewgraph.llm.components import components

SF = "/root/testdata/sf0.001"
SCHEMA = "doc_id long, text string, a string, n_chars long"
LONG = "word " * 5000 + "tail"
ODD = [(1, None, "x", 0), (2, "", "x", 0), (3, LONG, None, 5), (None, "no id here at all, but some words", "x", 1), (4, "same text in two rows of it here\n\nx", "x", 1), (4, "same text in two rows of it here\n\nx", "x", 1), (5, " \t\r\n\v\f", "x", 1)]


@pytest.fixture(scope="module")
def docs(spark):
    return spark.read.parquet(f"{SF}/documents.parquet")


@pytest.fixture(scope="module")
def odd(spark):
    return spark.createDataFrame(ODD, SCHEMA)


def test_bpe_agrees_with_the_library():
    codec = bpe.codec(P.path("byte_bpe_multi_50k.tiktoken"), P.PATTERN)
    library = tiktoken.Encoding("x", pat_str=P.PATTERN, mergeable_ranks=codec.vocabulary.ranks, special_tokens={})
    rng = random.Random(7)
    for _ in range(400):
        text = "".join(rng.choice("abcdethe ing  \n\té中文'st 12,.!<|endoftext|>") for _ in range(rng.randint(0, 80)))
        ids = codec.encode(text)
        assert np.frombuffer(ids, "<u4").tolist() == library.encode_ordinary(text)
        assert codec.decode(ids) == text.encode()


def test_bpe_prefixes_and_edits():
    vocabulary = bpe.codec(P.path("byte_bpe_multi_50k.tiktoken"), P.PATTERN).vocabulary
    own = bpe.PrefixEncoding(vocabulary, b"internat")
    own.append(b"ionalisation")
    assert own.tokens() == vocabulary.encode_piece(b"internationalisation") and own.tokens(8) == vocabulary.encode_piece(b"internat")
    own.replace(3, 5, b"XYZ")
    assert own.tokens() == vocabulary.encode_piece(b"intXYZnationalisation")
    text = b"the quick brown fox jumps over it, " * 60
    long, n = bpe.PrefixEncoding(vocabulary, text), vocabulary.longest
    long.replace(40, 43, b"stood")
    assert long.tokens() == vocabulary.encode_piece(text[:40] + b"stood" + text[43:]) and long.redone <= 5 + 2 * n + 40 < len(text)
    rng = random.Random(4)
    for _ in range(60):
        a, b = sorted((rng.randint(0, len(long.data)), rng.randint(0, len(long.data))))
        long.replace(a, min(b, a + 9), bytes(rng.choices(b"ab t,hexy", k=rng.randint(0, 6))))
        assert long.tokens() == vocabulary.encode_piece(long.data)


def test_packing_places_every_id_once(spark, docs, odd):
    reader = Tokenizer.from_file(P.path("byte_bpe_50k.json"))
    reader.encode_special_tokens = True
    texts = {r.doc_id: r.text for r in docs.collect()}
    got = packing.pack(docs, P.path("byte_bpe_50k.tiktoken"), P.PATTERN).toPandas()
    for doc, own in got.groupby("doc_id"):
        ids = [*reader.encode(texts[doc], add_special_tokens=False).ids, 1]
        assert own.length.sum() == len(ids) == own.doc_tokens.iloc[0]
        for r in own.itertuples():
            assert zlib.crc32(np.array(ids[r.start : r.start + r.length], "<u4").tobytes()) == r.ids_crc32
    for _, own in got.sort_values("offset").groupby("sequence_id"):
        assert own.offset.tolist() == [0, *own.length.cumsum().tolist()[:-1]] and own.length.sum() <= 2048
    assert got.length.sum() / (got.sequence_id.nunique() * 2048) > 0.95
    assert packing.pack(odd, P.path("byte_bpe_50k.tiktoken"), P.PATTERN).agg({"length": "sum"}).first()[0] > 5000
    assert packing.pack(odd.limit(0), P.path("byte_bpe_50k.tiktoken"), P.PATTERN).count() == 0


def test_cutting_stock_covers_demand():
    sizes, rng = packing.class_sizes(), np.random.default_rng(1)
    demand = np.bincount(np.searchsorted(sizes, rng.integers(1, 2049, 3000)), minlength=len(sizes))
    cuts, bound = packing.solve(demand, sizes)
    assert (sum(np.array(c.counts) * c.times for c in cuts) == demand).all()
    assert all(np.dot(c.counts, sizes) <= 2048 for c in cuts)
    assert sum(c.times for c in cuts) <= bound * 1.02 + 2


def test_simhash_components(spark, docs, odd):
    got = simhash.near_duplicates(docs.unionByName(docs.withColumnRenamed("doc_id", "d").selectExpr("d + 1000 as doc_id", "text", "lang", "source", "n_chars")), 3, 3).toPandas()
    fp, ids = got.fp.to_numpy(), got.doc_id.to_numpy()
    root = np.arange(len(fp))
    for _ in range(20):
        near = np.bitwise_count(fp[:, None] ^ fp[None, :]) <= 3
        root = np.where(near, root[None, :], len(fp)).min(axis=1)
    least = {r: ids[root == r].min() for r in set(root.tolist())}
    assert [least[r] for r in root.tolist()] == got.component_id.tolist()
    assert simhash.near_duplicates(odd, 3).count() == len(ODD) and simhash.near_duplicates(odd.limit(0), 3).count() == 0


def test_hot_signatures_lose_no_link(spark):
    rng = random.Random(2)
    base = rng.getrandbits(63)
    fps = list({base ^ sum(1 << b for b in rng.sample(range(63), rng.randint(0, 3))) for _ in range(300)})
    frame = spark.createDataFrame(list(enumerate(fps)), "id long, fp long").cache()
    one = components(hamming.links(frame, 3)).frame.count()
    assert components(hamming.links(frame, 3, group=16)).frame.count() == one == len(fps) - 1
    for k in range(5):
        plan = hamming.allocate(*hamming.bit_statistics(frame), k)
        assert sum(t + 1 for t in plan.thresholds) == k + 1 and sorted(b for g in plan.bits for b in g) == list(range(64))


def test_links_see_the_highest_bit(spark):
    fps = spark.createDataFrame([(1, 5), (2, 5 - (1 << 63)), (3, 5 - (1 << 63) + 2)], "id long, fp long")
    assert {(r.a, r.b) for r in hamming.links(fps, 3).collect()} == {(2, 1), (3, 1)}


def test_similar_texts_keep_one(spark):
    rng = random.Random(5)
    words = [f"w{rng.randint(0, 9999)}" for _ in range(200)]
    near = words[:100] + ["changed"] + words[101:]
    rows = [(1, " ".join(words)), (2, " ".join(near)), (3, " ".join(words[::-1])), (4, None), (5, ""), (6, " ".join(words)), (None, "x")]
    kept = simhash.keep_one(spark.createDataFrame(rows, "doc_id long, text string"))
    assert {r.doc_id for r in kept.collect()} == {1, 3, 4, 5, None}


def test_lines(spark, odd):
    line = "This is a line that stands in several documents of the corpus number 12"
    rows = [(1, f"alpha beta\n{line}"), (2, f"{line.upper()}!\nsomething else that is not repeated"), (3, line.replace("12", "99")), (4, "short line\nshort line"), (5, None)]
    got = {r.doc_id: r for r in lines.dedup(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    assert got[1].text == rows[0][1] and got[2].text == "something else that is not repeated" and got[3].text == "" and got[4].text == "short line" and got[5].text is None
    assert lines.dedup(odd).count() == len(ODD) and lines.dedup(odd.limit(0)).count() == 0


def test_similar_texts_at_the_bound(spark):
    rng = random.Random(9)
    draw = lambda n: [f"w{int(rng.paretovariate(0.7))}" for _ in range(n)]
    grams = lambda x: {tuple(x[i : i + 5]) for i in range(len(x) - 4)}
    rows, planted = [], 0
    for n in (60, 200, 600):
        for kind in ("append", "block", "words"):
            for _ in range(40):
                old = draw(n)
                new, m = list(old), n * 9 // 100
                if kind == "append":
                    new += draw(n * 23 // 100)
                elif kind == "block":
                    new[20 : 20 + m] = draw(m)
                else:
                    for i in rng.sample(range(n), max(1, n // 60)):
                        new[i] = "changed"
                a, b = grams(old), grams(new)
                if len(a & b) >= 0.8 * len(a | b):
                    rows += [(len(rows), " ".join(old)), (len(rows) + 1, " ".join(new))]
                    planted += 1
    kept = {r.doc_id for r in simhash.keep_one(spark.createDataFrame(rows, "doc_id long, text string")).select("doc_id").collect()}
    print("planted", planted, "found", len(rows) - len(kept))
    assert planted > 200 and len(rows) - len(kept) >= 0.99 * planted and all(i in kept for i in range(0, len(rows), 2))


def test_lines_find_edits_of_a_fifth(spark):
    rng = random.Random(5)
    word = lambda: "".join(rng.choice("abcdefghiklmnoprstuw") for _ in range(rng.randint(3, 9)))
    rows, planted = [], 0
    for n in (10, 20, 50):
        for kind in ("words", "block", "append"):
            for _ in range(40):
                old = [word() for _ in range(n)]
                new, m = list(old), max(1, n // 6)
                if kind == "words":
                    for i in rng.sample(range(n), m):
                        new[i] = word()
                elif kind == "block":
                    new[2 : 2 + m] = [word() for _ in range(m)]
                else:
                    new += [word() for _ in range(m)]
                if lines.alike(" ".join(old), " ".join(new), lines.SIMILARITY):
                    rows += [(len(rows), " ".join(old)), (len(rows) + 1, " ".join(new))]
                    planted += 1
    rows.append((len(rows), " ".join(word() for _ in range(20))))
    got = lines.dedup(spark.createDataFrame(rows, "doc_id long, text string"))
    gone = {r.doc_id for r in got.where("n_removed > 0").collect()}
    assert planted > 200 and len(gone) >= 0.97 * planted and all(i % 2 for i in gone)


def test_quality_against_plain_counts(spark, docs, odd):
    labels = spark.read.parquet(f"{SF}/labels.parquet")
    texts = {r.doc_id: r.text.encode() for r in docs.collect()}
    marks = {i: set() for i in texts}
    for r in labels.collect():
        if r.doc_id in marks:
            marks[r.doc_id].add((r.quality, r.toxic))
    good = {i for i, m in marks.items() if m == {(1, 0)}}
    bad = {i for i, m in marks.items() if any(t for _, t in m)}
    raw, trusted, every, toxic = (Counter() for _ in range(4))
    for i, text in texts.items():
        words = text.split()
        raw.update(own := quality.cells(words, quality.BUCKETS).tolist() if words else [])
        trusted.update(own if i in good else [])
        held = set(quality.stems(words).ravel().tolist()) if words else set()
        every.update(held)
        toxic.update(held if i in bad else [])
    total, seen = sum(raw.values()), sum(every.values())

    def ratio(c):
        p = (raw[c] + 1) / (total + quality.BUCKETS)
        return math.log((trusted[c] + quality.PRIOR * p) / (sum(trusted.values()) + quality.PRIOR) / p)

    def harm(c):
        expected = (every[c] + 1) / (seen + quality.TOXIC_BUCKETS) * sum(toxic.values())
        return math.log((toxic[c] + quality.TOXIC_PRIOR) / (expected + quality.TOXIC_PRIOR))

    got = quality.judge(docs, quality.fit_labelled(docs, labels)).collect()
    assert len(got) == len(texts)
    for r in got:
        words = texts[r.doc_id].split()
        n = len(words)
        windows = Counter(tuple(words[i : i + 5]) for i in range(n - 4))
        hit = {i + j for i in range(n - 4) if windows[tuple(words[i : i + 5])] > 1 for j in range(5)}
        lines_of = [x for x in texts[r.doc_id].split(b"\n") if x.split()]
        assert (r.n_words, r.n_repeat_words, r.n_dup_lines) == (n, len(hit), len(lines_of) - len(set(lines_of)))
        assert r.word_chars == sum(len(w.decode()) for w in words) and r.n_symbols == sum(texts[r.doc_id].count(c) for c in b"#*$%&|<>")
        score = sum(map(ratio, quality.cells(words, quality.BUCKETS).tolist())) / (2 * n - 1) if n else 0.0
        each = [max(harm(a), harm(b), quality.TOXIC_FLOOR) for a, b in quality.stems(words).T.tolist()]
        run = max((sum(each[i : i + 10]) for i in range(max(1, n - 9))), default=0.0)
        assert abs(r.score - score) < 1e-4 and abs(r.toxicity - run) < 1e-3
        assert r.base_failed == (n < 10 or 100 * len(hit) > 20 * n)
        if abs(score - quality.THRESHOLD) > 1e-4 and abs(run - quality.TOXIC_RUN) > 1e-3:
            assert r.kept == (not r.base_failed and score >= quality.THRESHOLD and run < quality.TOXIC_RUN)
    model = quality.fit(odd, odd.select("doc_id").limit(0))
    assert not model.weights.any() and model.toxic is None
    assert [r.kept for r in quality.judge(odd, model).where("doc_id in (1, 2, 5)").collect()] == [False] * 3
    assert quality.judge(odd.limit(0), model).count() == 0


def test_toxic_texts_of_held_out_labels(spark):
    """Learned from the labels of even documents, measured on the odd ones."""
    docs, labels = (spark.read.parquet(f"/root/testdata/sf0.1/{t}.parquet") for t in ("documents", "labels"))
    got = quality.judge(docs, quality.fit_labelled(docs, labels.where("doc_id % 2 = 0"))).where("not base_failed").join(labels.where("doc_id % 2 = 1 and quality = 1"), "doc_id").toPandas()
    caught, kept = (got[got.toxic == 1].toxicity >= quality.TOXIC_RUN).mean(), got[got.toxic == 0].kept.mean()
    print("toxic caught", caught, "of", (got.toxic == 1).sum(), "clean kept", kept)
    assert caught >= 0.45 and kept >= 0.97


def test_class_model(spark, docs, odd):
    got = brown.score(docs, "crc32(cast(doc_id as string)) % 7 = 2").toPandas()
    assert len(got) == 200 and (got.held_out == [zlib.crc32(str(i).encode()) % 7 == 2 for i in got.doc_id]).all()
    assert got.score[got.held_out].sum() > got.base_score[got.held_out].sum()
    assert np.isfinite(got.score).all() and brown.score(odd, "false").count() == len(ODD) and brown.score(odd.limit(0), "true").count() == 0


def test_exchange_separates_two_languages():
    left, right = np.array([0, 1, 2, 3, 0, 2]), np.array([1, 0, 3, 2, 1, 3])
    own = brown.exchange(left, right, np.array([50.0, 50, 50, 50, 9, 9]), 4, 2)
    assert len(set(own.tolist())) == 2


def test_shards_hold_their_limit(spark, docs, odd):
    got = sharding.assign(docs, 20_000).toPandas()
    sums = got.groupby("shard").n_bytes.sum()
    assert len(got) == 200 and (sums[~got.groupby("shard").oversized.any()] <= 20_000).all()
    one = sharding.assign(docs.selectExpr("1 as doc_id", "text"), 50_000).toPandas()
    assert len(one) == 200 and one.groupby("shard").n_bytes.sum().max() <= 50_000
    assert sharding.assign(odd, 100).count() == len(ODD) and sharding.assign(odd.limit(0), 100).count() == 0


def test_top_k(spark):
    rows = [(i, [float(x) for x in np.random.default_rng(i).normal(size=8)]) for i in range(300)] + [(300, None), (301, [None] * 8), (302, [float("nan")] * 8), (303, [])]
    got = topk.top_k(spark.createDataFrame(rows, "vec_id long, embedding array<double>"), "vec_id % 50 = 0", 5)
    data = np.floor(1024 * np.array([x for _, x in rows[:300]])).astype(int)
    for q in range(0, 300, 50):
        want = sorted((-int(data[i] @ data[q]), i) for i in range(300) if i != q)[:5]
        assert [(r.vec_id, r.score) for r in got.where(f"query_id = {q}").orderBy("rank").collect()] == [(i, -s) for s, i in want]


def test_roles(spark):
    def best(roles):
        table = chat.Repair(chat.Costs()).forward(roles, chat.START)
        return min(x[0] for x in table[-1] if x)

    assert best(["user", "assistant"]) == 0 and best(["user", "user"]) == 1 and best(["assistant"]) == 2 and best([None, "assistant"]) == 1 and best(["user", "assistant", "system"]) == 2
    rows = [(1, 0, "user", "a"), (1, 1, "user", "b"), (1, 2, "assistant", None), (None, 0, "odd", "x"), (2, 0, "assistant", "y")]
    frame = spark.createDataFrame(rows, "conv_id long, turn long, role string, text string")
    text = {r.conv_id: r.text for r in chat.rendered(chat.repair(frame)).collect()}
    assert text[1] == "<|user|>\na\n\nb<|end|>\n<|assistant|>\n<|end|>\n" and len(text) == 3


def test_long_conversations_repair_in_segments(spark, monkeypatch):
    rng = random.Random(3)
    roles = [rng.choice(["user", "assistant", "system", "x"]) for _ in range(60)]
    machine = chat.Repair(chat.Costs())
    table = machine.forward(roles, chat.START)
    want = min(x[0] for x in table[-1] if x)
    parts = [roles[i : i + 7] for i in range(0, 60, 7)]
    ways = chat.chain([machine.matrix(p) for p in parts])
    cost = sum(machine.forward(p, e)[-1][x][0] for p, (e, x, _) in zip(parts, ways, strict=True))
    assert cost == want and [w[0] for w in ways[1:]] == [w[1] for w in ways[:-1]]


def test_main_text(spark):
    page = "<html><body><nav>menu</nav><div class='x'><div class='story'><h1>T &amp; U</h1><p>one  two<br>three</p><p>four</p></div><div class='ad'>buy</div></div><section id='comments'><p>no</p></section><footer>f</footer></body></html>"
    frame = spark.createDataFrame([(1, "http://a/1", page), (2, "http://a/2", page.replace("one", "uno" * 40)), (3, None, None), (4, "http://a/3", "")], "page_id long, url string, html string")
    got = {r.page_id: r.text for r in html_wrappers.extract(frame).collect()}
    assert got[1] == "T & U\none two three\nfour" and got[3] == "" and got[4] == ""
    assert html_wrappers.extract(frame.limit(0)).count() == 0


def test_pipeline_keeps_columns(spark):
    import corpus_pipeline as c
    from skewgraph.llm.common import Shared

    now = spark.read.parquet(f"{SF}/documents.parquet")
    for name, stage in c.STAGES[:-1]:
        out = Shared(stage(spark, now, SF), "stage").frame
        assert out.columns == now.columns and 0 < out.count() <= now.count(), name
        now = out


def test_byte_bpe_digests(spark, docs, odd):
    path = P.path("byte_bpe_multi_50k.tiktoken")
    library = tiktoken.Encoding("x", pat_str=P.PATTERN, mergeable_ranks=bpe.Vocabulary.load_ranks(path), special_tokens={})
    texts = {r.doc_id: r.text for r in docs.collect()}
    got = llm_queries.op3_byte_bpe(spark, SF).collect()
    assert len(got) == len(texts)
    for r in got:
        ids = library.encode_ordinary(texts[r.doc_id])
        assert r.n_tokens == len(ids) and r.ids_sha256 == hashlib.sha256(np.array(ids, "<u4").tobytes()).hexdigest() and r.decoded_sha256 == hashlib.sha256(texts[r.doc_id].encode()).hexdigest()
    assert bpe.round_trip(odd, path, P.PATTERN).where("n_tokens = 0").count() == 2 and bpe.round_trip(odd.limit(0), path, P.PATTERN).count() == 0


def test_fingerprints_bit_by_bit(spark, docs):
    got = {r.doc_id: int(r.fingerprint, 16) for r in llm_queries.op5_simhash(spark, SF).collect()}
    for r in docs.collect():
        words = r.text.encode().lower().split()
        shingles = [b" ".join(words[i : i + 3]) for i in range(max(1, len(words) - 2))] if words else []
        hashes = [xxh64_intdigest(x, 42) for x in shingles]
        assert got[r.doc_id] == sum(1 << b for b in range(64) if 2 * sum(h >> b & 1 for h in hashes) > len(hashes))


def test_line_recall_against_brute_force(spark, docs):
    """Distinct lines that share three words in a row and reach the similarity: nearly all end in one group."""
    marked = lines.line_hashes(docs)
    distinct = marked.groupBy("h").agg(F.min(F.struct("doc_id", "line")).alias("first"), F.min("fp").alias("fp"), F.min("size").alias("size"), F.min("bands").alias("bands")).select(F.col("h").alias("id"), "fp", "size", "bands", "first.doc_id", "first.line").cache()
    texts = {r.doc_id: r.text.encode().decode().lower().encode().split(b"\n") for r in docs.collect()}
    normal = {r.id: b" ".join(lines.normal_words(texts[r.doc_id][r.line])).decode() for r in distinct.collect()}
    root = {i: i for i in normal}

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    for r in lines.line_links(docs, distinct).collect():
        assert lines.alike(normal[r.a], normal[r.b], lines.SIMILARITY)
        root[find(r.a)] = find(r.b)
    runs = {}
    for i, line in normal.items():
        words = line.split(" ")
        for k in range(len(words) - 2):
            runs.setdefault(tuple(words[k : k + 3]), set()).add(i)
    words_of = {i: set(line.split(" ")) for i, line in normal.items()}
    pairs = {p for own in runs.values() for p in combinations(sorted(own), 2)}
    alone = lambda a, b: len(words_of[a] & words_of[b]) < 0.4 * max(len(words_of[a]), len(words_of[b]))
    pairs = [p for p in pairs if not alone(*p)]  # too few common words
    near = [p for p, good in zip(pairs, lines.all_alike([(normal[a], normal[b]) for a, b in pairs], lines.SIMILARITY), strict=True) if good] if pairs else []
    found = sum(find(a) == find(b) for a, b in near)
    print("near pairs", len(near), "found", found)
    assert len(near) > 20 and found >= 0.9 * len(near)


def test_line_stage_leaves_no_equal_lines(spark, docs):
    import corpus_pipeline as c

    before = {r.doc_id: r.text for r in docs.collect()}
    after = {r.doc_id: r.text for r in c.line_dedup(spark, docs, SF).collect()}
    normal = lambda text: [b" ".join(w) for x in text.lower().encode().split(b"\n") if (w := lines.normal_words(x))]
    kept = Counter(x for t in after.values() for x in normal(t))
    assert max(kept.values()) == 1
    gone = Counter(x for t in before.values() for x in normal(t)) - kept
    distinct = [x.decode() for x in kept]
    lost = [x.decode() for x in gone if x not in kept]
    for x in lost[:40]:  # an edited line goes only if a like one stays, directly or over others
        assert any(lines.alike(x, y, lines.SIMILARITY) for y in [*distinct, *lost] if y != x)
    assert all(not before[i].split() or all(x in gone for x in normal(before[i])) for i in before.keys() - after.keys())


def test_near_dedup_stage_against_all_pairs(spark, docs):
    import corpus_pipeline as c

    sets = {}
    for r in docs.collect():
        w = r.text.encode().lower().split()
        sets[r.doc_id] = {tuple(w[i : i + 5]) for i in range(max(1, len(w) - 4))} if w else set()
    root = {i: i for i in sets}

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    for a, b in combinations(sorted(sets), 2):
        x, y = sets[a], sets[b]
        if x and y and 5 * min(len(x), len(y)) >= 4 * max(len(x), len(y)) and len(x & y) >= 0.8 * len(x | y):
            a, b = find(a), find(b)
            root[max(a, b)] = min(a, b)
    assert {r.doc_id for r in c.near_dedup(spark, docs, SF).collect()} == {i for i in sets if find(i) == i}


def test_class_model_base_by_hand(spark, docs):
    counts, texts = Counter(), {r.doc_id: [*r.text.encode().lower().split(), b" "] for r in docs.collect()}
    held = {i: zlib.crc32(str(i).encode()) % 7 == 2 for i in texts}
    for i, words in texts.items():
        if not held[i]:
            counts.update(words)
    total = sum(counts.values())
    for r in llm_queries.op7_class_model(spark, SF).collect():
        words = texts[r.doc_id]
        base = sum(math.log10((counts[w] + 1) / (total + len(counts) + 1)) for w in words)
        assert (r.held_out, r.n_tokens, r.train_tokens, r.n_known) == (held[r.doc_id], len(words), total, sum(counts[w] > 0 for w in words))
        assert abs(r.base_score - base) < 1e-6 * max(1, abs(base))


def test_exchange_ends_where_no_move_gains():
    rng = np.random.default_rng(3)
    previous, following = rng.integers(0, 13, 60), rng.integers(0, 12, 60)
    n = rng.integers(1, 30, 60).astype(float)

    def gain(own):
        table = np.zeros((4, 3))
        np.add.at(table, (np.append(own, 3)[previous], own[following]), n)
        flow = lambda x: (x * np.log(np.maximum(x, 1))).sum()
        return flow(table) - flow(table.sum(axis=0)) - flow(table[:3].sum(axis=1))

    own = brown.exchange(previous, following, n, 12, 3, sweeps=100)
    for u in range(12):
        for c in range(3):
            moved = own.copy()
            moved[u] = c
            assert gain(moved) <= gain(own) + 1e-5


def test_roles_against_all_paths():
    costs = chat.Costs()

    def cheapest(state, roles):
        if not roles:
            return 0
        return min(c + cheapest(to, roles[1:]) for c, to, _, _ in chat.steps(state, roles[0], costs))

    rng = random.Random(8)
    machine = chat.Repair(costs)
    for _ in range(150):
        roles = [rng.choice(["user", "assistant", "system", None]) for _ in range(rng.randint(1, 6))]
        table = machine.forward(roles, chat.START)
        best = min((x[0], s) for s, x in enumerate(table[-1]) if x)
        assert best[0] == cheapest(chat.START, roles)
        told = [s for s, _, between in chat.Repair.path(table, best[1]) for s in ([between, s] if between else [s])]
        actions = [a for _, a, _ in chat.Repair.path(table, best[1])]
        state = chat.START
        for s, action in zip(told, [a for a, (_, _, b) in zip(actions, chat.Repair.path(table, best[1]), strict=True) for a in (["insert", a] if b else [a])], strict=True):
            assert s in chat.LEGAL[state] or action == "merge" and s == state
            state = s


def test_alignment_is_a_longest_common_one():
    rng = random.Random(9)
    for _ in range(200):
        x, y = ("".join(rng.choices("abc", k=rng.randint(0, 7))) for _ in range(2))
        best = max(len(s) for n in range(len(x) + 1) for s in combinations(x, n) if _inside(s, y))
        pairs = html_wrappers._common(list(x), list(y))
        assert len(pairs) == best and all(x[i] == y[j] for i, j in pairs) and pairs == sorted(pairs)


def _inside(s, y):
    rest = iter(y)
    return all(c in rest for c in s)


def test_the_wrapper_decides(spark):
    page = lambda i: f"<html><body><div class='top'>Site</div><article><h1>Title {i}</h1><div class='box'>Read our paper daily</div><p>{'text %d ' % i * (i + 3)}</p><ul><li><a href='/{i}'>next {i}</a></li></ul><section><p>part {i * 7}</p></section></article></body></html>"
    plain = "<html><body><div class='top'>Site</div><main><p>a page of another kind</p></main></body></html>"
    rows = [(i, "http://h/x", page(i)) for i in range(12)] + [(50, "http://h/y", plain), (60, "http://one/", page(3)), (61, "http://one/", page(3))]
    long = "<article><p>" + "long text " * 60000 + "</p></article>"
    rows += [(70, "http://long/", long)]
    frame = spark.createDataFrame(rows, "page_id long, url string, html string").withColumn("wrapper", F.lit("x")).withColumn("_h", F.lit("y"))
    got = {r.page_id: r.text for r in html_wrappers.extract(frame).collect()}
    assert got[3] == "Title 3\n" + " ".join(["text 3"] * 6) + "\npart 21" and got[50] == "a page of another kind"
    assert got[60] == got[61] and "Read our paper daily" in got[60] and "next 3" in got[60]  # a page alone knows no template
    assert len(got[70]) == len("long text " * 60000) - 1 and len(got) == len(rows)
    nothing = html_wrappers.extract(frame.limit(0))
    assert nothing.count() == 0


CLASHES = ["gone", "_doc", "_gone", "_given", "_cuts", "n_lines", "n_removed", "_id", "_conv", "bands", "h", "fp", "size", "held", "trusted", "cell", "kept", "score", "ids", "shard", "_key"]


def test_clashing_columns(spark, odd):
    wide = odd.select("*", *(F.lit(i).alias(c) for i, c in enumerate(CLASHES)))
    out = lines.dedup(wide)
    assert out.columns == [c for c in wide.columns if c not in ("n_lines", "n_removed")] + ["n_lines", "n_removed"] and out.count() == len(ODD)
    own = lines.dedup(wide, measures=False)
    assert own.columns == wide.columns and own.agg(F.min("n_lines"), F.max("gone")).first() == (5, 0)
    model = quality.fit(wide, wide.select("doc_id"))
    assert quality.judge(wide, model, keep_columns=True).columns == wide.columns and quality.judge(wide, model).count() == len(ODD)
    assert simhash.keep_one(wide).columns == wide.columns and simhash.near_duplicates(wide, 3).count() == len(ODD)
    assert brown.score(wide, "false").count() == len(ODD) and sharding.assign(wide, 100).count() == len(ODD)
    assert packing.pack(wide, P.path("byte_bpe_50k.tiktoken"), P.PATTERN).agg(F.countDistinct("doc_id")).first()[0] == 5
    vectors = spark.createDataFrame([(i, [1.0 * i, 2.0], 7) for i in (0, 1, 1, 2, 3)], "vec_id long, embedding array<double>, width int").withColumn("score", F.lit(1))
    got = topk.top_k(vectors, "vec_id = 0", 3).orderBy("rank").collect()
    assert [(r.vec_id, r.score) for r in got] == [(1, 4 * 1024 * 1024)] * 2 + [(2, 4 * 1024 * 1024)]
    assert topk.top_k(vectors.limit(0), "vec_id = 0").count() == 0
    turns = spark.createDataFrame([(1, 0, "user", "a", 1), (1, 0, "user", "a", 1)], "conv_id long, turn long, role string, text string, chunk int")
    assert [r.action for r in chat.repair(turns).collect()] == ["keep", "merge"] and chat.repair(turns.limit(0)).count() == 0


def test_top_k_in_lanes(spark, monkeypatch):
    rows = [(i, [float(x) for x in np.random.default_rng(i).normal(size=4)]) for i in range(90)]
    frame = spark.createDataFrame(rows, "vec_id long, embedding array<double>")
    want = sorted(map(tuple, topk.top_k(frame, "vec_id % 30 = 0", 4).collect()))
    monkeypatch.setattr(topk, "BESIDE_BYTES", 0)
    monkeypatch.setattr(topk, "BLOCK", 16)
    assert sorted(map(tuple, topk.top_k(frame, "vec_id % 30 = 0", 4).collect())) == want
    few = topk.top_k(frame.limit(3), "vec_id >= 0", 10)
    assert few.count() == 6
    huge = spark.createDataFrame([(0, [1e12]), (1, [1e12])], "vec_id long, embedding array<double>")
    with pytest.raises(Exception, match="64 bits"):
        topk.top_k(huge, "vec_id = 0").collect()


def test_pipeline_over_empty_and_odd_tables(spark, odd):
    import corpus_pipeline as c

    for table in (odd, odd.limit(0)):
        for name, stage in c.STAGES[:-1]:
            assert stage(spark, table, SF).columns == table.columns, name
        assert c.packed(spark, table, SF).count() >= 0


def test_exchange_goes_on_until_none_moves():
    pair = np.unique(np.random.default_rng(0).integers(0, 400, (1500, 2)), axis=0)
    found = lambda *sweeps: brown.exchange(pair[:, 0], pair[:, 1], np.ones(len(pair)), 400, 6, *sweeps)
    assert (found() == found(1000)).all() and (found() != found(8)).any()


def test_best_classes_of_rare_words_against_whole_likelihoods():
    rng = np.random.default_rng(5)
    classes, table = 4, rng.integers(50, 400, (5, 4)).astype(float)
    for own in range(classes):
        context, count = np.array([(own + 1) % 4, 4, 5 + (own + 2) % 4]), np.array([3, 9, 11])  # after a class, at the beginning, before a class

        def whole(c):
            t = table.copy()
            for x, n in zip(context, count):
                at, to = ((x, own), (x, c)) if x <= classes else ((own, x - 5), (c, x - 5))
                t[at] -= n
                t[to] += n
            return brown.likelihood(t)

        found = brown._gains(table, np.zeros(3, np.int64), context, count, np.array([own]), 1e-6)[0]
        assert abs(whole(found) - max(map(whole, range(classes)))) < 1e-9


def test_rare_words_of_one_ending_part(spark, monkeypatch):
    kept, run = [], brown._exchanged

    def caught(blocks, start, shards, *more):
        model, moved = run(blocks, start, shards, *more)
        rows = blocks.frame.toArrow().to_pylist()
        answers = moved.frame.where("block is not null").toArrow()
        for x in rows:
            own = brown._given(x, answers.filter(pa.compute.equal(answers["block"], x["block"])), shards, "classes", np.uint16)
            kept.append((model, dict(zip(np.frombuffer(x["words"], np.uint64).tolist(), own.tolist()))))
        return model, moved

    monkeypatch.setattr(brown, "_exchanged", caught)
    texts = [f"le x{i}ing la chat" if i % 2 else f"der y{i}ing das hund" for i in range(120)]
    got = brown.score(spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string").coalesce(1), "false", share=0.02, classes=10).collect()
    assert len(got) == 120 and len(kept) == 1
    model, of = kept[0]
    lines = [[of[xxh64_intdigest(w)] for w in [*t.encode().split(), b" "]] for t in texts]
    assert len({x[1] for x in lines}) > 1  # all of them stood in one class: that of their ending
    assert model.class_tokens.tolist() == np.bincount(np.concatenate(lines), minlength=10).tolist()
    table = np.zeros((11, 10))
    for x in lines:
        np.add.at(table, ([10, *x[:-1]], x), 1)
    unigram = (table.sum(axis=0) + 1) / (table.sum() + 10)
    assert np.allclose(model.transition, np.log10((table + brown.BACK * unigram) / (table.sum(axis=1, keepdims=True) + brown.BACK)))


def test_bands_of_distances_against_whole_ones():
    rng = random.Random(3)
    rows, columns, most, want = [], [], [], []
    while len(rows) < 300:
        letters = "ab" if len(rows) % 2 else "abcdefghiéñ漢 "
        a = [rng.choice(letters) for _ in range(rng.randint(2, 400))]
        b = [rng.choice(letters) if rng.random() < 0.1 else x for x in a if rng.random() > 0.1] or ["a"]
        a, b = sorted(("".join(a), "".join(b)), key=len, reverse=True)
        d = lines.edit_distance(a, b) if a != b else 0
        k = min(len(a) - 1, max(0, d + rng.choice([-3, -1, 0, 1, 20])))
        if len(a) - len(b) <= k:
            rows, columns, most, want = [*rows, a], [*columns, b], [*most, k], [*want, d <= k]
    assert lines._within(rows, columns, np.array(most)).tolist() == want == list(map(lines._near, rows, columns, most))
    assert 60 < sum(want) < 240


def test_few_pairs_of_a_family_are_compared(monkeypatch):
    """Lines that differ in one word each: one group, found with few comparisons, and joined by few links."""
    import pyarrow as pa

    words = [f"telling{i}" for i in range(40)]
    texts = [" ".join(words[:i] + ["changed"] + words[i + 1 :]) for i in range(40)]
    found = lines._digested([t.encode() for t in texts])
    fp, marks = simhash.majority(found.words, found.n_words), simhash.bands(found.words, found.n_words, lines.BANDS, lines.ROWS)
    same = np.flatnonzero(marks[:, 0] == Counter(marks[:, 0].tolist()).most_common(1)[0][0])
    n = len(same)
    part = pa.RecordBatch.from_pydict({"sig": pa.array([7] * n, pa.int64()), "at": pa.array([0] * n, pa.int64()), "fp": fp.view(np.int64)[same], "id": pa.array(same.astype(np.int64)), "bands": marks[same].tolist(), "text": [texts[i] for i in same]})
    compared = []
    monkeypatch.setattr(lines, "all_alike", lambda p, s, f=lines.all_alike: compared.extend(p) or f(p, s))
    links = [(a, b) for x in lines._verifier(lines.K, lines.SIMILARITY)([part]) for a, b in zip(*x.to_pydict().values(), strict=True)]
    root = hamming.roots(40, *np.array(links).T)
    assert n > 20 and len(set(root[same].tolist())) == 1 and len(compared) <= 2 * n and len(links) <= 2 * n


def test_near_dedup_links_by_simhash(spark, monkeypatch):
    """SimHashes alone, without a MinHash band, join lightly edited texts."""
    rng = random.Random(7)
    rows = []
    for i in range(20):
        words = [f"w{rng.randint(0, 9999)}" for _ in range(400)]
        rows += [(2 * i, " ".join(words)), (2 * i + 1, " ".join([*words[:200], "changed", *words[201:]]))]

    def none(k, ratio):
        def work(batches):
            for b in batches:
                yield b.select(["id", "id"]).slice(0, 0).rename_columns(["a", "b"])

        return work

    monkeypatch.setattr(simhash, "linker", none)
    kept = {r.doc_id for r in simhash.keep_one(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    assert {i for i in kept if i % 2 == 0} == set(range(0, 40, 2)) and len(kept) <= 22


def test_bpe_looks_up_tokens_of_fitting_ends_only():
    looked = []

    class Counted(dict):
        def get(self, key, default=None):
            looked.append(key)
            return dict.get(self, key, default)

    ranks = bpe.Vocabulary.load_ranks(P.path("byte_bpe_multi_50k.tiktoken"))
    v = bpe.Vocabulary(ranks)
    v.ranks = Counted(ranks)
    piece = " unüberlegtheitsfolgenzzqx".encode() * 3
    library = tiktoken.Encoding("x", pat_str=".+", mergeable_ranks=ranks, special_tokens={})
    assert v.encode_piece(piece) == library.encode_ordinary(piece.decode())
    assert len(looked) < 8 * len(piece)


def test_blocks_are_read_without_copies():
    import pyarrow as pa

    cell = bytes(range(8)) * (1 << 18)
    batch = pa.RecordBatch.from_pydict({"block": [1, 2], "words": [cell, cell]})
    held, most = pa.total_allocated_bytes(), 0
    for table in (batch, pa.Table.from_batches([batch])):
        for i, x in enumerate(brown._rows(table)):
            assert x["block"] == i + 1 and bytes(x["words"]) == cell
            assert np.shares_memory(np.frombuffer(x["words"], np.uint8), np.frombuffer(batch.column("words").buffers()[2], np.uint8))
            most = max(most, pa.total_allocated_bytes() - held)
    assert most == 0


def test_edit_bands_reach_only_cells_from_which_a_path_returns():
    random, kept = np.random.default_rng(3), []
    for _ in range(150):
        a = "".join(random.choice(list("abcé"), 40 + random.integers(120)))
        b = list(a)
        for at in random.integers(len(a) - 20, size=random.integers(1, 30)):
            b[at : at + random.integers(3)] = random.choice(list("abcé"), random.integers(3)).tolist()
        kept.append(sorted((a, "".join(b)), key=len, reverse=True))
    far = [lines.edit_distance(a, b) for a, b in kept]
    most = [max(len(a) - len(b), d + i % 3 - 1) for i, ((a, b), d) in enumerate(zip(kept, far, strict=True))]
    want = [d <= m for d, m in zip(far, most, strict=True)]
    assert lines._within([a for a, _ in kept], [b for _, b in kept], np.array(most)).tolist() == want and 0 < sum(want) < len(want)
    assert [lines._near(a, b, m) for (a, b), m in zip(kept, most, strict=True)] == want
    assert lines._reach("a" * 100, "a" * 100, 40) == 20 and lines._reach("a" * 100, "a" * 90, 40) == 25


def test_pairs_of_several_batches_are_compared_together(monkeypatch):
    texts, calls, own = [f"words of line {i // 2} that is long enough {'again' if i % 2 else 'anew'}" for i in range(40)], [], lines.all_alike
    monkeypatch.setattr(lines, "all_alike", lambda *a: calls.append(len(a[0])) or own(*a))
    bands = pa.FixedSizeListArray.from_arrays(pa.array(np.arange(40 * lines.BANDS, dtype=np.int32)), lines.BANDS).cast(pa.list_(pa.int32()))
    cols = [pa.array(np.arange(40) // 2), pa.array(np.zeros(40, np.int64)), pa.array(np.zeros(40, np.int64)), pa.array(np.arange(40)), bands, pa.array(texts)]
    whole = pa.RecordBatch.from_arrays(cols, ["sig", "at", "fp", "id", "bands", "text"])
    out = pa.Table.from_batches(list(lines._verifier(lines.K, 0.8)([whole.slice(i, 4) for i in range(0, 40, 4)])))
    assert sorted(zip(*(out[c].to_pylist() for c in ("a", "b")), strict=True)) == [(i, i + 1) for i in range(0, 40, 2)] and sum(calls) == 20
    assert sum(n > 0 for n in calls) <= 2


def _line_batch(ids, fps, marks):
    return pa.RecordBatch.from_arrays([pa.array(ids), pa.array(fps.view(np.int64)), pa.array(np.full(len(ids), 40, np.int32)), lines._as_bytes(marks)], ["id", "fp", "size", "bands"])


def test_lines_move_in_blocks_and_meet_under_each_band():
    """A cell for each shard instead of a row for each band; the lines that meet are those of brute force, hot signatures cut or not."""
    rng = np.random.default_rng(5)
    n = 300
    marks = rng.integers(0, 40, (n, lines.BANDS)).astype(np.int32)
    marks[:60, 3] = 7
    fps, ids = rng.integers(0, 1 << 63, n, dtype=np.uint64), np.arange(n) * 1_000_003 - 50
    fps[:60] = fps[0] ^ (np.uint64(1) << rng.integers(0, 63, 60).astype(np.uint64))
    batch = _line_batch(ids, fps, marks)
    sig = lines._signatures(marks)
    near = np.bitwise_count(fps[:, None] ^ fps[None, :]) <= lines.K
    want = {(int(ids[i]), int(ids[j])) for i, j in combinations(range(n), 2) if near[i, j] and (marks[i] == marks[j]).any()}
    root = hamming.roots(n, *(np.searchsorted(ids, np.array(x)) for x in zip(*want, strict=True)))
    values, counts = np.unique(sig, return_counts=True)
    for hot in (values[:0], np.sort(values[counts > 20])):
        cut = -(-counts[np.searchsorted(values, hot)] // 10)
        out = list(lines._dealer(hot, cut, 4)([batch.slice(0, 100), batch.slice(100)]))
        assert sum(len(x) for x in out) <= 4 and all(len(x) for x in out)
        rows = sorted(((s, c) for x in out for s, c in zip(*x.to_pydict().values(), strict=True)), key=lambda x: x[0])
        parts = [pa.RecordBatch.from_arrays([pa.array([s], pa.int32()), pa.array([c], pa.binary())], ["shard", "rows"]) for s, c in rows]
        groups = {}
        for x in lines._candidates(lines.K, 0.8)(parts):
            for s, at, i in zip(*x.to_pydict().values(), strict=True):
                groups.setdefault((s, at), set()).add(i)
        assert all(len(g) > 1 for g in groups.values())
        met = {p for g in groups.values() for p in combinations(sorted(g), 2)}
        assert want and want <= met
        held = hamming.roots(n, *(np.searchsorted(ids, np.array(x)) for x in zip(*(want & met), strict=True)))
        assert (held == root).all()


def test_frequent_bands_are_counted_over_chunks():
    marks = np.arange(40 * lines.BANDS, dtype=np.int32).reshape(40, -1)
    marks[:30, 2] = -5
    out = list(lines._counter([_line_batch(np.arange(40), np.zeros(40, np.uint64), marks).select(["bands"])]))
    assert [x.to_pydict() for x in out] == [{"sig": [int(lines._signatures(marks)[0, 2].view(np.int64))], "n": [30]}]


def test_distinct_lines_are_the_first_of_each_digest(spark):
    rows = [(i % 7 - 3, f"a line of some words {'abcde'[i % 5]}\nanother line\n\na line of some words {'abcde'[i % 5]}") for i in range(40)] + [(-(1 << 62), "another line"), (5, None)]
    marked = lines.line_hashes(spark.createDataFrame(rows, "doc_id long, text string").repartition(3), packed=True).cache()
    want = marked.groupBy("h").agg(F.min(F.struct("doc_id", "line")).alias("first"), F.min("fp"), F.min("size"), F.count("*")).collect()
    got = lines.distinct_lines(marked).collect()
    assert {(r.id, r.doc_id, r.line, r.fp, r.size, r.n) for r in got} == {(r.h, *r.first, *r[2:]) for r in want} and len(got) == len(want) == 6
    bands = {r.h: r.bands for r in lines.line_hashes(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    assert all(np.frombuffer(r.bands, np.int32).tolist() == bands[r.id] for r in got)
    assert lines.distinct_lines(marked.limit(0)).count() == 0
