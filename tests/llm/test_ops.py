"""Each operator against a brute-force version or held-out labels, and on odd tables."""

import hashlib
import os
import random
import re
import zlib
from collections import Counter, defaultdict

import numpy as np
import public_tokenizers
import pyarrow as pa
import pytest
import tiktoken
import xxhash

from roilens.llm import alike, bpe, chat, components, edit_embedding, licenses, mixing, quality_pu, quality_rules, registry, simhash, substring, textscan, toxicity

WORD = re.compile(r"[^\x20\x09-\x0D]+")
ODD = [
    (1, "a b c d e f g h i j k l m n o p", "en", "s1", 31), (2, None, None, None, None), (3, "", "en", None, 0), (4, "   \n\t ", "en", "s1", 6),
    (5, "a b c d e f g h i j k l m n o p", "en", "s2", 31), (5, "a b c d e f g h i j k l m n o p", "en", "s2", 31), (None, "x y z", "en", "s1", 5),
    (None, "x y z", "en", "s1", 5), (7, "é ü 日本 \U0001f600 wörd " * 3000, "de", "s3", 1), (8, "one", "en", "s2", 3), (9, "one\x0btwo", "en", "s2", 7),
]
SCHEMA = "doc_id long, text string, lang string, source string, n_chars long"
TEXTS = [r[1] for r in ODD]


@pytest.fixture(scope="module")
def odd(spark):
    from pyspark.sql import functions as F

    df = spark.createDataFrame(ODD, SCHEMA)
    for clash in ("score", "held_out", "size", "target", "fp", "seed", "mark", "part", "notices", "token_ids", "component_id", "spans"):
        df = df.withColumn(clash, F.lit(0))
    return df


@pytest.fixture(scope="module")
def empty(odd):
    return odd.limit(0)


def rows(df):
    return [tuple(r) for r in df.collect()]


# ---- scanning


def test_scan_counts_words_lines_and_repeats():
    words = ["a", "b", "c", "dd", "é", "日本"]
    rng = random.Random(1)
    texts = ["".join(rng.choice(words) + rng.choice([" ", "\n", "\t", "  "]) for _ in range(rng.randrange(0, 80))) for _ in range(60)] + [None, "", "x"]
    counts, _ = quality_rules.statistics(pa.array(texts, pa.string()))
    for t, got in zip(texts, counts.tolist(), strict=True):
        t = t or ""
        w = WORD.findall(t)
        lines = [x for x in t.split("\n") if WORD.search(x)]
        runs = Counter(tuple(w[i : i + 5]) for i in range(len(w) - 4))
        inside = {j for i in range(len(w) - 4) if runs[tuple(w[i : i + 5])] > 1 for j in range(i, i + 5)}
        assert got == [len(w), sum(map(len, w)), sum(c in "#*$%&|<>" for c in t), len(lines) - len(set(lines)), len(inside)]


def test_equal_words_have_equal_hashes_wherever_they_stand():
    s = textscan.Scan(pa.array(["ab cd ab", "xx ab"]))
    h = s.word_hashes().tolist()
    assert h[0] == h[2] == h[4] and len(set(h)) == 3


# ---- 1 licences


def test_license_survives_layout_and_spelling(spark):
    body = licenses.TEXTS["MIT"]
    altered = "Copyright (c) 2020 Someone\n\n" + body.upper().replace("SUBLICENSE", "sub-licence").replace(",", " ,").replace('"', "“")
    df = spark.createDataFrame([(1, body), (2, altered), (3, body + " more"), (4, "text\nReleased under the MIT Licence."), (5, None)], "doc_id long, text string")
    got = {r.doc_id: (r.license, r.notices, r.n_notices) for r in licenses.scan(df).collect()}
    assert got[1][0] == got[2][0] == "MIT" and got[3][0] is None
    assert got[4] == (None, "MIT", 1) and got[5] == (None, None, 0)


def test_license_registry_is_an_argument(spark, monkeypatch):
    bodies = spark.createDataFrame([("own", "One line.\nTwo lines."), ("notice", "See the licence."), ("nothing", " . ")], "known string, body string")
    df = spark.createDataFrame([(1, "one LINE\n\ntwo, lines"), (1, "See the license!\nx\nsee the licence"), (None, ""), (2, None)], "doc_id long, text string")
    for few in (100, 0):  # broadcast, and joined by a shuffle
        monkeypatch.setattr(licenses, "FEW_KNOWN", few)
        got = sorted(((r.doc_id, r.license, r.notices, r.n_notices) for r in licenses.scan(df, bodies).collect()), key=str)
        assert got == sorted([(1, "own", None, 0), (1, None, "notice", 2), (None, None, None, 0), (2, None, None, 0)], key=str)


# ---- 2 quality


def test_prior_and_risk_of_planted_mixture():
    rng = np.random.default_rng(3)
    pos = rng.normal(1, 1, (2000, len(quality_pu.FEATURES)))
    unl = np.concatenate([rng.normal(1, 1, (2800, pos.shape[1])), rng.normal(-1.5, 1, (1200, pos.shape[1]))])
    net = quality_pu.train(pos, unl)
    assert abs(net.prior - 0.7) < 0.08
    assert ((net.score(unl) > 0.5) == (np.arange(4000) < 2800)).mean() > 0.95
    assert quality_pu.train(pos[:0], unl).score(unl[:2]).tolist() == [0.5, 0.5]


def test_quality_held_out(spark):
    got = registry.op2_quality_classifier(spark, "/root/testdata/sf0.1").toPandas()
    assert all(bool(h) == (zlib.crc32(str(i).encode()) % 4 == 2) for i, h in zip(got.doc_id, got.held_out, strict=True))
    m = got.merge(spark.read.parquet("/root/testdata/sf0.1/labels.parquet").toPandas(), on="doc_id")
    m = m[m.held_out]
    assert (m.predicted == m.quality).mean() > 0.97


# ---- 3 mixing


def water_fill(sizes, weights, total, cap):
    left, out = dict(sizes), {}
    while left:
        w = sum(weights[s] for s in left)
        share = {s: (total - sum(out.values())) * weights[s] / w for s in left}
        over = [s for s in left if share[s] >= cap * sizes[s]]
        if not over:
            return out | share
        for s in over:
            out[s] = cap * sizes[s]
            del left[s]
    return out


def test_mix_matches_iterated_resharing(spark):
    got = registry.op3_mix_sources(spark, "/root/testdata/sf0.01").toPandas()
    docs = spark.read.parquet("/root/testdata/sf0.01/documents.parquet").toPandas()
    docs["size"] = [len(WORD.findall(t or "")) for t in docs.text]
    sizes = docs.groupby("source")["size"].sum().to_dict()
    weights = {s: (5, 2, 1)[i % 3] for i, s in enumerate(sorted(sizes))}
    want = water_fill(sizes, weights, 1.5 * sum(sizes.values()), 2)
    m = got.merge(docs[["doc_id", "source"]], on="doc_id")
    for s, g in m.groupby("source"):
        assert abs(g.target.iloc[0] - want[s]) < 1e-6 * want[s]
        assert abs(g.taken.sum() - want[s]) <= g["size"].max()
    assert (m.taken <= 2 * m["size"]).all() and abs(m.groupby("source").target.first().sum() - 1.5 * docs["size"].sum()) < 1e-3
    again = registry.op3_mix_sources(spark, "/root/testdata/sf0.01").toPandas()
    assert sorted(map(tuple, got.values.tolist())) == sorted(map(tuple, again.values.tolist()))


def test_mix_of_rows_that_agree_in_everything(spark):
    same = [(None, "a b c d e f", "s1")] * 1000 + [(3, "x y z", "s2")] * 500 + [(i, "k l", "s3") for i in range(900)]
    docs = spark.createDataFrame(same, "doc_id long, text string, source string").repartition(5, "text").cache()
    got = mixing.mix(docs).toPandas()
    sizes = {"s1": 6000, "s2": 1500, "s3": 1800}
    want = water_fill(sizes, {"s1": 5, "s2": 2, "s3": 1}, 1.5 * 9300, 2)
    for s, size in sizes.items():
        mine = got[got.source_size == size]
        assert abs(mine.taken.sum() - want[s]) <= 2 * mine["size"].max()
    taken = mixing.mixed_rows(docs).groupBy("source").count().collect()
    assert all(abs(r["count"] * {"s1": 6, "s2": 3, "s3": 2}[r.source] - want[r.source]) <= 12 for r in taken)


# ---- 4 SimHash


def simhash_slow(text):
    w = [x for x in WORD.findall("".join(c.lower() if "A" <= c <= "Z" else c for c in text or ""))]
    sh = [" ".join(w[i : i + 3]) for i in range(len(w) - 2)] if len(w) >= 3 else [" ".join(w)] * bool(w)
    h = [xxhash.xxh64_intdigest(x.encode(), seed=42) for x in sh]
    return sum(1 << i for i in range(64) if 2 * sum(x >> i & 1 for x in h) > len(h))


def components_slow(links, nodes):
    root = {n: n for n in nodes}

    def find(n):
        while root[n] != n:
            n = root[n]
        return n

    for a, b in links:
        a, b = find(a), find(b)
        root[max(a, b)] = min(a, b)
    return {n: find(n) for n in nodes}


def test_simhash_against_all_pairs(spark):
    got = registry.op4_simhash(spark, "/root/testdata/sf0.01").collect()
    texts = {r.doc_id: r.text for r in spark.read.parquet("/root/testdata/sf0.01/documents.parquet").collect()}
    fp = {i: simhash_slow(t) for i, t in texts.items()}
    ids = sorted(fp)
    arr = np.array([fp[i] for i in ids], np.uint64)
    links = [(ids[i], ids[j]) for i in range(len(ids)) for j in (np.flatnonzero(np.bitwise_count(arr[i] ^ arr[i + 1 :]) <= 2) + i + 1).tolist()]
    want = components_slow(links, ids)
    assert {r.doc_id: (r.fingerprint, r.component_id) for r in got} == {i: (f"{fp[i]:016x}", want[i]) for i in ids}


def test_near_duplicate_stage_equals_all_pairs_jaccard(spark):
    import corpus_pipeline

    rng = random.Random(3)
    texts = []
    for share in (0.005, 0.01, 0.02, 0.03, 0.04):
        for _ in range(12):
            base = words(rng, rng.randrange(60, 400))
            texts.append(" ".join(base))
            for _ in range(4):
                texts.append(" ".join(w if rng.random() > share else f"new{rng.randrange(10**6)}" for w in base))
    chain = words(rng, 300)  # neighbours alike, ends not
    for i in range(12):
        texts.append(" ".join(chain[:i * 20] + words(random.Random(i), 3) + chain[i * 20 + 3 :]))
    sets = []
    for t in texts:
        w = t.split()
        sets.append({tuple(w[i : i + 5]) for i in range(len(w) - 4)})
    links = [(i, j) for i in range(len(sets)) for j in range(i) if len(sets[i] & sets[j]) >= 0.8 * len(sets[i] | sets[j])]
    comp = components_slow(links, range(len(texts)))
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    got = {r.doc_id for r in corpus_pipeline.near_duplicates(spark, docs, "").collect()}
    assert got == set(comp.values()) and len(got) < len(texts)
    assert {r.doc_id for r in simhash.keep_one(docs).collect()} != got


def jaccard_components(texts):
    sets = [{tuple(w[i : i + 5]) for i in range(max(1, len(w) - 4))} for w in (t.split() for t in texts)]
    links = [(i, j) for i in range(len(sets)) for j in range(i) if len(sets[i] & sets[j]) >= 0.8 * len(sets[i] | sets[j])]
    return components_slow(links, range(len(texts)))


def test_a_crowd_of_variants_equals_all_pairs(spark, monkeypatch):
    rng = random.Random(8)
    base = words(rng, 150)
    texts = []
    for n in range(260):  # one to six edits: some pairs just over 0.8, most under it
        w = list(base)
        for _ in range(rng.randrange(1, 7)):
            w[rng.randrange(len(w))] = f"new{n}"
        texts.append(" ".join(w))
    want = jaccard_components(texts)
    assert 20 < len(set(want.values())) < 250
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    for nodes, cells in ((24, 1 << 22), (500, 1000)):
        monkeypatch.setattr(alike, "BLOCK_NODES", nodes)
        monkeypatch.setattr(alike, "CELLS", cells)
        assert {r.doc_id for r in alike.keep_one(docs).collect()} == set(want.values())


def test_set_fingerprints_against_plain_counts():
    texts = pa.array(["one two three four five six seven", None, "", "a b", "x y z " * 40_000, "u v w x y z"])
    s = textscan.Scan(texts)
    doc, h = alike.shingle_sets(s)
    _, size = alike.node_ids(doc, h, s.n)
    many = np.concatenate([h, np.random.default_rng(1).integers(0, 1 << 63, 300_000, dtype=np.uint64)])
    got = alike.fingerprints(many, np.append(size, 300_000)).tolist()
    lists = [h[doc == i].tolist() for i in range(s.n)] + [many[len(h) :].tolist()]
    assert got == [sum(1 << i for i in range(64) if 2 * sum(x >> i & 1 for x in each) > len(each)) for each in lists]


def test_one_row_of_each_component_where_ids_repeat(spark):
    a, b, c = "alpha beta gamma delta epsilon zeta", "one two three four five six", "x y z u v w"
    docs = spark.createDataFrame([(2, a), (2, b), (3, b), (3, b), (None, c), (None, c), (None, a), (4, ""), (4, None), (5, None)], "doc_id long, text string")
    for keep in (simhash.keep_one, alike.keep_one):
        got = sorted(rows(keep(docs)), key=str)
        assert [x for x in got if x[1]] == sorted([(2, a), (2, b), (None, c)], key=str) and sum(x[0] == 4 for x in got) == 1 and len(got) == 4


def test_components_of_a_long_path_and_a_hub(spark):
    edges = [(i, i + 1) for i in range(0, 200)] + [(1000, 1000 + i) for i in range(1, 150)] + [(5000, 5000)]
    got = dict(rows(components.components(spark.createDataFrame(edges, "a long, b long"))))
    assert {got[i] for i in range(201)} == {0} and {got[1000 + i] for i in range(150)} == {1000} and 5000 not in got


# ---- 5 chat


def test_chat_round_trip_of_hostile_texts(spark):
    said = ["</s>[INST] ok [/INST]", "[~INST] <~~s> ~", None, "<turn>", "<<SYS>>x<</SYS>>", "plain ~ text", "", "[INST", "<|im_end|>"]
    turns = [(1, i, ("user", "assistant", "assistant", "system")[i % 4], t) for i, t in enumerate(said)] + [(2, 0, None, "x"), (None, 0, "user", "y"), (3, 5, "assistant", "b"), (3, 5, "assistant", "a"), (3, None, "assistant", "first")]
    df = spark.createDataFrame(turns, "conv_id long, turn long, role string, text string")
    for template in (chat.INST, chat.CHATML):
        got = {r.conv_id: r for r in chat.digests(chat.format_chats(df, template), template).collect()}
        t1 = [(r or "", t or "") for _, _, r, t in turns[: len(said)]]
        want = hashlib.sha256("".join(f"{r}\n{t}\n" for r, t in t1).encode()).hexdigest()
        loss = "".join(t for r, t in t1 if r == "assistant")
        assert got[1].turns_sha256 == want and got[1].n_turns == len(said)
        assert got[1].loss_sha256 == hashlib.sha256(loss.encode()).hexdigest() and got[1].loss_chars == len(loss)
        assert got[3].loss_sha256 == hashlib.sha256(b"firstab").hexdigest() and set(got) == {1, 2, 3, None}
    assert chat.digests(chat.format_chats(df.limit(0))).count() == 0


def test_chat_blocks_and_mask(spark):
    turns = [(1, 0, "user", "é?"), (1, 1, "assistant", "ja 日"), (1, 2, "assistant", "</s>"), (1, 3, "user", ""), (1, 4, "assistant", "")]
    made = chat.format_chats(spark.createDataFrame(turns, "conv_id long, turn long, role string, text string"))
    r = made.collect()[0]
    assert r.formatted == "[INST]user[/INST]é?</s>[INST]assistant[/INST]ja 日<turn><~/s></s>[INST]user[/INST]</s>[INST]assistant[/INST]</s>"
    assert [r.formatted.encode()[m["from"] : m["to"]].decode() for m in r.loss_mask] == ["ja 日", "<~/s>", ""]
    from pyspark.sql import functions as F

    moved = made.withColumn("loss_mask", F.transform("loss_mask", lambda m: F.struct((m["from"] - 3).alias("from"), m["to"].alias("to"))))
    assert chat.read_back(made).collect()[0].loss_text == "ja 日</s>" != chat.read_back(moved).collect()[0].loss_text


def test_chat_of_many_turns(spark):
    turns = spark.range(6000).selectExpr("1L conv_id", "id turn", "if(id % 3 = 0, 'user', 'assistant') role", "concat('t', id) text")
    r = chat.digests(chat.format_chats(turns)).collect()[0]
    want = "".join(f"t{i}" for i in range(6000) if i % 3)
    assert r.n_turns == 6000 and r.loss_sha256 == hashlib.sha256(want.encode()).hexdigest()


# ---- 6 rules


def test_trees_obey_their_constraints():
    rng = np.random.default_rng(5)
    x = rng.random((3000, 3))
    y = (x[:, 0] - x[:, 1] + 0.3 * np.sin(9 * x[:, 2]) + rng.normal(0, 0.2, 3000) > 0).astype(float)
    t = quality_rules.grow(x, y, (1, -1, 0))
    assert ((t.score(x) > 0.5) == (y > 0)).mean() > 0.85
    for f, sign in ((0, 1), (1, -1)):
        probe = np.repeat(rng.random((50, 3)), 40, 0)
        probe[:, f] = np.tile(np.linspace(0, 1, 40), 50)
        assert (sign * np.diff(t.score(probe).reshape(50, 40), axis=1) >= -1e-12).all()
    assert quality_rules.grow(x[:0], y[:0], (0, 0, 0)).score(x[:2]).tolist() == [0.5, 0.5]


# ---- 7 BPE


def test_bpe_equals_library_and_round_trips():
    b = bpe.tokenizer(public_tokenizers.path(registry.RANK_FILE), public_tokenizers.PATTERN)
    lib = tiktoken.Encoding("own", pat_str=public_tokenizers.PATTERN, mergeable_ranks=b.ranks, special_tokens={})
    rng = random.Random(7)
    texts = [t or "" for t in TEXTS] + ["a" * 3000, "ab" * 2000 + "é" * 500, "<|endoftext|>", "\n\n \x1c x", "".join(chr(rng.randrange(32, 0x3000)) for _ in range(4000)), "日本語テキスト" * 50]
    for t in texts:
        ids = b.encode(t)
        assert ids == lib.encode_ordinary(t) and b.decode(ids) == t.encode()


def test_bpe_of_a_table_equals_library(spark, monkeypatch):
    for entries, long_list in ((150_000, 1 << 22), (40, 10)):  # a memory that is given up all the time, packed links
        monkeypatch.setattr(bpe, "MEMO_ENTRIES", entries)
        monkeypatch.setattr(bpe, "LONG_LIST", long_list)
        b = bpe.ByteBPE(public_tokenizers.path(registry.RANK_FILE), public_tokenizers.PATTERN)
        lib = tiktoken.Encoding("own", pat_str=public_tokenizers.PATTERN, mergeable_ranks=b.ranks, special_tokens={})
        texts = [r.text or "" for r in spark.read.parquet("/root/testdata/sf0.001/documents.parquet").collect()]
        for lo in range(0, len(texts), 30):
            for t, ids in zip(texts[lo : lo + 30], b.encode_many(texts[lo : lo + 30]), strict=True):
                assert ids.tolist() == lib.encode_ordinary(t)
            assert len(b.young) <= entries and len(b.old) <= entries
    for r in registry.op7_byte_bpe(spark, "/root/testdata/sf0.001").join(spark.read.parquet("/root/testdata/sf0.001/documents.parquet"), "doc_id").collect():
        ids = lib.encode_ordinary(r.text or "")
        assert (r.n_tokens, r.ids_sha256) == (len(ids), hashlib.sha256(" ".join(map(str, ids)).encode()).hexdigest())
        assert r.decoded_sha256 == hashlib.sha256((r.text or "").encode()).hexdigest()


# ---- 8 passages


def words(rng, n):
    return ["".join(rng.choice("abcdefghijk") for _ in range(rng.randrange(2, 8))) for _ in range(n)]


def test_planted_passages_are_found_and_cut(spark):
    rng = random.Random(11)
    shared, fuzzy = words(rng, 80), words(rng, 120)
    docs, planted = [], set()
    for i in range(40):
        body = words(rng, 300)
        if i % 4 == 0:
            body[100:100] = shared
            planted.add(i)
        if i % 10 == 5:
            altered = [w if rng.random() > 0.06 else "zz" + w for w in fuzzy]
            body[50:50] = altered
            planted.add(i)
        docs.append((i, " ".join(body)))
    docs += [(100, None), (101, ""), (None, " ".join(shared))]
    df = spark.createDataFrame(docs, "doc_id long, text string")
    got = substring.duplicated_passages(df).collect()
    assert {r.doc_id for r in got} | {r.first_doc_id for r in got} == planted
    exact = [r for r in got if r.doc_id % 4 == 0 and r.doc_id % 10 != 5]
    assert {(r.from_word, r.to_word) for r in exact} == {(100, 180)}
    left = {r.doc_id: r.text for r in substring.without_passages(df).collect() if r.doc_id is not None}
    mark = " ".join(shared[20:60])
    assert mark in left[0] and not any(mark in (left[i] or "") for i in range(4, 40, 4)) and left[100] is None and left[101] == ""


def test_passages_with_changes_cycles_and_scattered_first_holders(spark):
    rng = random.Random(12)
    docs, want = [], set()

    def add(*parts):
        docs.append((len(docs), " ".join(" ".join(p) for p in parts)))
        return len(docs) - 1

    def apart():
        return words(rng, rng.randrange(20, 60))

    changed = []
    for _ in range(60):  # 60 words, 10 % of them changed
        own = words(rng, 60)
        at = set(rng.sample(range(60), 6))
        add(apart(), own, apart())
        changed.append(add(apart(), [f"zz{i}" if i in at else w for i, w in enumerate(own)], apart()))
    for period in (1, 3, 8, 12, 16, 20):  # exact, but repeating itself
        line = words(rng, period)
        own = (line * 80)[:80]
        add(apart(), own, apart())
        want.add(add(apart(), own, apart()))
    for _ in range(10):  # pieces of 15 words stand in six earlier documents, the whole in two later ones
        own = words(rng, 60)
        for i in range(0, 60, 9):
            add(apart(), own[i : i + 15], apart())
        add(apart(), own, apart())
        want.add(add(apart(), own, apart()))
    clean = {add(apart(), apart()) for _ in range(40)}
    got = {r.doc_id for r in substring.duplicated_passages(spark.createDataFrame(docs, "doc_id long, text string")).collect()}
    assert want <= got and not clean & got
    assert len(got & set(changed)) >= 0.9 * len(changed)


def test_passages_where_ids_repeat(spark):
    rng = random.Random(13)
    s, a, b, c = words(rng, 80), words(rng, 40), words(rng, 40), words(rng, 90)
    docs = [(1, a + s), (2, b + s), (2, c), (2, c), (None, s)]
    df = spark.createDataFrame([(i, " ".join(w)) for i, w in docs], "doc_id long, text string")
    got = [tuple(r)[:4] for r in substring.duplicated_passages(df).collect()]
    assert got == [(2, 1, 40, 120)]
    left = sorted(rows(substring.without_passages(df)), key=str)
    assert left == sorted([(1, " ".join(a + s)), (2, " ".join(b)), (2, " ".join(c)), (2, " ".join(c)), (None, " ".join(s))], key=str)


def test_chains_match_quadratic_dynamic_programme():
    rng = random.Random(2)
    for _ in range(30):
        n = rng.randrange(1, 40)
        p = sorted(rng.sample(range(200), n))
        q = [rng.randrange(200) for _ in range(n)]
        best = [5.0] * n
        for i in range(n):
            for j in range(i):
                if p[j] < p[i] and q[j] < q[i]:
                    best[i] = max(best[i], best[j] + 5 - 0.05 * (p[i] - p[j] + q[i] - q[j]))
        chain = substring.chains(p, q, 5, 0.05, 10**9)[0]
        score = 5.0 * len(chain) - 0.05 * (p[chain[-1]] - p[chain[0]] + q[chain[-1]] - q[chain[0]])
        assert abs(score - max(best)) < 1e-9
        assert sorted(x for c in substring.chains(p, q) for x in c) == list(range(n))


def test_any_long_common_run_shares_a_seed():
    rng = random.Random(4)
    for _ in range(20):
        common = " ".join(words(rng, substring.K + substring.WINDOW - 1))
        a, b = (" ".join(words(rng, rng.randrange(0, 30))) + " " + common + " " + " ".join(words(rng, rng.randrange(0, 30))) for _ in range(2))
        s = textscan.Scan(pa.array([a, b]))
        at, h = substring.winnow(s)
        d = s.word_doc[at]
        assert set(h[d == 0].tolist()) & set(h[d == 1].tolist())


# ---- 9 edit embedding


def test_edit_study_against_plain_reading(spark, odd):
    docs = [(i, "".join(random.Random(i).choice("abcdef é\U0001f600") for _ in range(i * 7 % 90))) for i in range(60)]
    df = spark.createDataFrame(docs, "doc_id long, text string")
    got = {r.doc_id: r for r in edit_embedding.edit_study(df, 5).collect()}
    text = dict(docs)
    for i in range(60):
        following = text[i - 1 if i else 59]
        want = edit_embedding.edited_text(text[i], following)
        assert got[i].n_chars == len(text[i]) and got[i].edited_sha256 == hashlib.sha256(want.encode()).hexdigest()
        a, b, c = edit_embedding.embed([text[i], want, following])
        assert got[i].near_edited == (a == b).mean() and got[i].near_next == (a == c).mean()
        assert got[i].fingerprint == edit_embedding.to_hex(a[None])[0]


def test_every_range_has_a_partition_of_its_own(spark):
    from pyspark.sql import functions as F

    df = spark.range(3000).select((F.col("id") % 17).cast("int").alias("part"))
    for parts in (list(range(17)), list(range(0, 17, 2))):
        some = df.where(F.col("part").isin(parts)).repartition(len(parts), edit_embedding._own_partition(spark, parts))
        assert some.select(F.spark_partition_id().alias("p"), "part").distinct().groupBy("p").count().select("count").distinct().collect() == [(1,)]


def test_likeness_falls_with_edits():
    rng = random.Random(1)
    base = "".join(rng.choice("abcdefghijklmnop ") for _ in range(3000))
    means = []
    for edits in (0, 10, 100, 3000):
        t = list(base)
        for _ in range(edits):
            k = rng.randrange(len(t))
            t[k : k + rng.randrange(2)] = rng.choice(["", "x", "yz"])
        a, b = edit_embedding.embed([base, "".join(t)])
        means.append((a == b).mean())
    assert means[0] == 1.0 and means[0] > means[1] > means[2] > means[3] and means[1] > 0.6


def test_near_links_find_close_fingerprints(spark):
    rng = random.Random(9)
    docs = []
    for i in range(30):
        base = "".join(rng.choice("abcdefgh ") for _ in range(2000))
        docs += [(2 * i, base), (2 * i + 1, base[:1900] + "!")]
    fps = edit_embedding.fingerprints(spark.createDataFrame(docs, "doc_id long, text string"))
    of = {r.doc_id: r.fingerprint for r in fps.collect()}
    got = {tuple(sorted((r.a, r.b))) for r in edit_embedding.near_links(fps, 0.8).collect()}
    want = {tuple(sorted((of[2 * i], of[2 * i + 1]))) for i in range(30)}
    assert len(got & want) >= 0.9 * len(want) and not got - want


# ---- 10 toxicity


def test_near_links_in_crowded_buckets_equal_all_bucket_mates(spark):
    rng = np.random.default_rng(edit_embedding.SEED + 1)
    picks = [sorted(rng.choice(128, 6, replace=False).tolist()) for _ in range(32)]
    r = random.Random(8)
    step = [[r.choice("123456789abcdef") for _ in range(128)]]
    for _ in range(40):  # a large group: neighbours alike, ends not
        step.append([r.choice("123456789abcdef") if r.random() < 0.1 else x for x in step[-1]])
    marks = {"".join(x) for x in step}
    for x in step:  # each bucket also gets a least member that is like none of its mates
        marks |= {"".join(d if i in p else "0" for i, d in enumerate(x)) for p in picks}
    marks = sorted(marks)
    key = [{(b, "".join(m[i] for i in p)) for b, p in enumerate(picks)} for m in marks]
    arr = np.array([list(m) for m in marks])
    near = [(i, j) for i in range(len(marks)) for j in np.flatnonzero((arr[:i] == arr[i]).mean(1) >= 0.8).tolist() if key[i] & key[j]]
    at = {m: i for i, m in enumerate(marks)}
    fps = spark.createDataFrame([(m,) for m in marks], "fingerprint string")
    got = [(at[x.a], at[x.b]) for x in edit_embedding.near_links(fps, 0.8).collect()]
    assert components_slow(got, range(len(marks))) == components_slow(near, range(len(marks)))
    chain = [at["".join(x)] for x in step]
    assert len({components_slow(got, range(len(marks)))[i] for i in chain}) == 1


def test_near_edit_groups_hold_every_row(spark):
    rng = random.Random(4)
    base = "".join(rng.choice("abcdefgh ") for _ in range(3000))
    rows = [(7, base), (3, base[:2990] + "zz"), (9, base), (None, base), (5, "other " * 300), (1, None), (2, "")]
    got = edit_embedding.near_groups(spark.createDataFrame(rows, "doc_id long, text string")).collect()
    of = {r.doc_id: r.component_id for r in got}
    assert len(got) == len(rows)
    assert of == {7: 3, 3: 3, 9: 3, None: 3, 5: 5, 1: 1, 2: 1}
    empty = spark.createDataFrame([], "doc_id long, text string")
    assert edit_embedding.near_groups(empty).count() == 0


def test_toxicity_held_out_and_sentences(spark):
    got = registry.op10_toxicity(spark, "/root/testdata/sf0.1").toPandas()
    m = got.merge(spark.read.parquet("/root/testdata/sf0.1/labels.parquet").toPandas(), on="doc_id")
    m = m[m.held_out]
    toxic, clean = m[m.toxic == 1], m[m.toxic == 0]
    assert toxic.predicted.mean() > 0.8 and clean.predicted.mean() < 0.01
    assert toxic[toxic.predicted == 1].worst_sentence.notna().all() and got.score.between(0, 1).all()


def test_noisy_or_locates_the_planted_sentence():
    rng = random.Random(3)
    texts, y = [], []
    for i in range(400):
        s = [" ".join(words(rng, 6)) for _ in range(5)]
        if i % 4 == 0:
            s[rng.randrange(5)] += " vilest thing"
        texts.append(". ".join(s) + ".")
        y.append(i % 4 == 0)
    model = toxicity.train(pa.array(texts), np.array(y, int))
    p = model.score(pa.array(texts))
    assert ((p > 0.5) == np.array(y)).mean() > 0.99
    assert all("vilest" in w[1] for w, t in zip(model.worst(pa.array(texts)), y, strict=True) if t)
    assert model.score(pa.array([None, ""], pa.string())).tolist() == [0, 0]


# ---- odd tables through every operator and stage


def test_odd_rows_have_results(spark, odd, empty):
    labels = spark.createDataFrame([(1, 1, 0), (5, 0, 1), (None, 1, 1), (7, None, None)], "doc_id long, quality int, toxic int")
    for docs, n in ((odd, len(ODD)), (empty, 0)):
        assert licenses.scan(docs).count() == n
        assert quality_pu.score(docs, quality_pu.fit(spark, docs, labels)).count() == n
        assert quality_rules.judge(docs, quality_rules.fit(spark, docs, labels)).count() == n
        assert toxicity.score(docs, toxicity.fit(spark, docs, labels)).count() == n
        assert mixing.mix(docs).count() == n
        assert simhash.near_duplicates(docs).count() == n
        assert bpe.digests(docs, public_tokenizers.path(registry.RANK_FILE), public_tokenizers.PATTERN).count() == n
        assert edit_embedding.edit_study(docs).count() == n
        substring.duplicated_passages(docs).count()


def test_stages_keep_columns_and_one_of_each(spark, odd, empty):
    import corpus_pipeline

    one = simhash.keep_one(odd)
    assert one.columns == odd.columns
    # components: the a..p text, the empty ones, x y z (no id), the long one, 'one', 'one two'
    assert sorted((r.doc_id is None, r.doc_id or 0) for r in one.collect()) == [(False, 1), (False, 2), (False, 7), (False, 8), (False, 9), (True, 0)]
    assert substring.without_passages(odd).columns == odd.columns and substring.without_passages(odd).count() == len(ODD)
    mixed = mixing.mixed_rows(odd)
    planned = {(r.doc_id, r.size): r.repeats for r in mixing.mix(odd).collect()}
    seen = Counter((r.doc_id, len(WORD.findall(r.text or ""))) for r in mixed.collect())
    copies = Counter((r[0], len(WORD.findall(r[1] or ""))) for r in ODD)
    assert mixed.columns == odd.columns and all(seen.get(k, 0) == v * copies[k] for k, v in planned.items())
    docs = empty
    for _, stage in corpus_pipeline.STAGES:
        docs = stage(spark, docs, "/root/testdata/sf0.001")
        assert docs.count() == 0


def test_pipeline_on_the_smallest_tables(spark, sf):
    import corpus_pipeline

    docs = spark.read.parquet(f"{sf}/documents.parquet")
    kept = defaultdict(list)
    for name, stage in corpus_pipeline.STAGES:
        before, docs = docs, stage(spark, docs, sf)
        path = registry.table(spark, sf, "documents").columns
        assert [c for c in docs.columns if c != "token_ids"] == path
        from roilens.llm.common import written

        docs = written(docs, "stage")
        kept[name] = (before.count(), docs.count())
    assert kept["near duplicates"][1] < kept["near duplicates"][0] and kept["substring dedup"][0] == kept["substring dedup"][1]
    b = bpe.tokenizer(public_tokenizers.path(registry.RANK_FILE), public_tokenizers.PATTERN)
    assert all(b.decode(r.token_ids).decode() == r.text for r in docs.limit(50).collect())


def test_query_names_follow_the_list():
    names = list(registry.queries())
    assert [n.split("_")[0] for n in names] == [f"op{i}" for i in range(1, 11)] + ["pipeline"]
    assert os.path.exists(public_tokenizers.path(registry.RANK_FILE))
