"""The corpus operators against brute force on a small table of awkward documents: nulls, empty and long texts, ties, repeated rows, clashing names."""

import hashlib
import random
import re
import zlib
from collections import Counter, defaultdict

import numpy as np
import pytest

from fixflow.llm import bpe, decontam, graph_ann, jaccard, langid, mixing, parse_dedup, sharding, substring, token_store

SCHEMA = "doc_id long, text string, lang string, key string, notes string, score string"
WORD = re.compile(rb"[^\x20\x09-\x0D]+")


def corpus():
    r = random.Random(5)
    vocab = ["".join(r.choice("abcdefgh") for _ in range(r.randint(2, 7))) for _ in range(400)]
    text = lambda n: " ".join(r.choice(vocab) for _ in range(n))
    base, passage = text(300), text(60)
    near = base.split()
    near[17] = "changed"
    rows = [(1, base, "en"), (2, base, "en"), (3, " ".join(near), "fr"), (4, text(80) + "\n" + passage + "\t" + text(30), "fr"), (5, passage + " " + text(50), "de"), (6, None, "en"), (7, "", None), (8, "?!", "en"), (9, "one", None), (10, "one", "de"), (11, "ONE", "de")]
    rows += [(12, text(5000), "en"), (13, "a" * 3000, "en"), (14, " ".join(["same"] * 200), "en"), (15, "Ünïcödé ß İ " + text(50), "de"), (None, base, "en"), (None, text(30), None), (16, "dup row " + text(25), "en"), (16, None, None)]
    rows += [(100 + k, text(r.randint(1, 200)), r.choice(["en", "fr"])) for k in range(40)]
    rows += [(200 + k, " ".join(w if r.random() > 0.02 else "x%d" % k for w in base.split()), "en") for k in range(60)]  # a family past FEW
    return rows


@pytest.fixture(scope="module")
def rows():
    return corpus()


@pytest.fixture(scope="module")
def docs(spark, rows):
    return spark.createDataFrame([(*x, "k", "n", "s") for x in rows], SCHEMA).repartition(5)


def words(text):
    return WORD.findall((text or "").encode())


def test_bpe(docs, rows):
    path = bpe.vocabulary()
    lib = bpe.load(path).library
    want = sorted((str(i), len(e.ids), hashlib.sha256(" ".join(map(str, e.ids)).encode()).hexdigest(), hashlib.sha256(lib.decode(e.ids, skip_special_tokens=False).encode()).hexdigest()) for (i, t, _), e in zip(rows, lib.encode_batch([t or "" for _, t, _ in rows], add_special_tokens=False)))
    assert sorted((str(r.doc_id), r.n_tokens, r.ids_sha256, r.decoded_sha256) for r in bpe.digests(docs, path).collect()) == want
    back = bpe.decode_ids(bpe.encode_ids(docs, path), path).select("ids", "decoded").collect()
    assert all(r.decoded == lib.decode(r.ids, skip_special_tokens=False) for r in back)


def test_token_store(docs, rows):
    path = bpe.vocabulary()
    lib = bpe.load(path).library
    uri, manifest = token_store.write_store(docs, path, shards=3)
    got = token_store.look_up(docs, uri, manifest, with_ids=True).collect()
    want = defaultdict(list)
    for i, t, _ in rows:
        want[i].append(lib.encode(t or "", add_special_tokens=False).ids + [1])
    assert len(got) == len(rows)
    at = 0
    for r in sorted(got, key=lambda r: r.start):
        assert r.start == at and list(r.ids) in want[r.doc_id]
        assert r.ids_crc32 == zlib.crc32(np.array(r.ids, "<u4").tobytes())
        at += r.n_tokens
    ids = [r.doc_id for r in sorted(got, key=lambda r: r.start)]
    assert ids == sorted(ids, key=lambda x: (x is not None, x))
    strangers = docs.sparkSession.createDataFrame([(10**9,), (17,)], "doc_id long")
    assert token_store.look_up(strangers, uri, manifest).count() == 0


def test_substring(docs, rows):
    got = {(r.doc_id, r.n_words): (r.n_removed, r.kept_sha256) for r in substring.remove_repeats(docs, 20).collect() if r.doc_id is not None}
    seen = set()
    for i, t, _ in sorted((x for x in rows if x[0] is not None), key=lambda x: (x[0], x[1] is None)):
        w = words(t)
        out = [False] * len(w)
        for k in range(len(w) - 19):
            if tuple(w[k : k + 20]) in seen:
                out[k : k + 20] = [True] * 20
            seen.add(tuple(w[k : k + 20]))
        assert got[(i, len(w))] == (sum(out), hashlib.sha256(b" ".join(x for x, o in zip(w, out) if not o)).hexdigest()), i
    left = {r.doc_id: r for r in substring.remove_repeats(docs, 20, with_text=True).where("doc_id < 16").collect()}
    assert left[6].text is None and left[2].text == "" and left[1].key == "k" and left[12].text == rows[11][1]


def test_parse_dedup(docs, rows):
    length = 120
    count = Counter()
    for _, t, _ in rows:
        b = (t or "").encode()
        count.update(b[k : k + length] for k in range(len(b) - length + 1))
    want = []
    for i, t, _ in rows:
        b = (t or "").encode()
        out = np.zeros(len(b), bool)
        for k in range(len(b) - length + 1):
            if count[b[k : k + length]] > 1:
                out[k : k + length] = True
        kept = np.frombuffer(b, np.uint8)[~out].tobytes()
        want.append((str(i), len(b), int(out.sum()), int(np.diff(out.astype(int), prepend=0).clip(0).sum()), hashlib.sha256(kept).hexdigest()))
    assert sorted((str(r[0]), *r[1:]) for r in parse_dedup.remove_repeated_bytes(docs, length).collect()) == sorted(want)


def test_jaccard(docs, rows):
    k, percent = 4, 85
    sets = {}
    for n, (i, t, _) in enumerate(rows):
        w = words((t or "").lower() if (t or "").isascii() else "".join(c.lower() if c.isascii() else c for c in t or ""))
        sets[n] = frozenset(tuple(w[j : j + k]) for j in range(len(w) - k + 1)) if len(w) >= k else frozenset([tuple(w)] if w else [])
    up = {n: n for n in sets}

    def root(x):
        while up[x] != x:
            x = up[x]
        return x

    own = [n for n in sets if sets[n] and rows[n][0] is not None]
    for a in own:
        for b in own:
            if a < b and 100 * len(sets[a] & sets[b]) >= percent * len(sets[a] | sets[b]):
                up[root(a)] = root(b)
    least = {}
    for n in own:
        least[root(n)] = min(least.get(root(n), 10**9), rows[n][0])
    want = sorted((rows[n][0], len(sets[n]), least[root(n)] if n in own else rows[n][0]) for n in sets if rows[n][0] is not None)
    got = jaccard.near_duplicates(docs, k, percent).collect()
    assert sorted(tuple(r) for r in got if r.doc_id is not None) == want
    assert len(got) == len(rows)


def test_language(spark, docs):
    train = spark.createDataFrame([("the cat and the dog " * 5, "en"), ("le chat et la souris " * 5, "fr"), (None, "en"), ("x", None)], "text string, lang string")
    told = langid.predict(spark.createDataFrame([(1, "the dog"), (2, "la souris"), (3, None), (4, "12 !?")], "doc_id long, text string"), langid.learn(train), keep=["doc_id"])
    got = {r.doc_id: r for r in told.collect()}
    assert [got[k].lang_pred for k in (1, 2, 3, 4)] == ["en", "fr", "und", "und"] and got[3].score == 0 and 0 <= got[1].score <= 1
    assert {r.lang_pred for r in langid.predict(docs, langid.learn(train.limit(0)), keep=["doc_id"]).collect()} == {"und"}


def test_mixing(docs, rows):
    train = docs.where("doc_id is null or doc_id % 3 <> 0")
    tok = lambda t: [w.lower() for w in words(t)] + [b"\n"]
    c = Counter(w for i, t, _ in rows if i is None or i % 3 for w in tok(t))
    n, v = sum(c.values()), len(c)
    got = mixing.score_texts(docs, train).collect()
    want = sorted((len(tok(t)), sum(c[w] > 0 for w in tok(t)), round(sum(np.log10((c[w] + 1) / (n + v + 1)) for w in tok(t)), 6)) for _, t, _ in rows)
    assert sorted((r.n_tokens, r.n_known, round(r.base_score, 6)) for r in got) == want
    assert all(r.train_tokens == n and r.score < 0 for r in got)


def test_mixing_gains_over_its_base_and_over_chance(spark):
    """Documents held out score above the unigram base; the known bit is learned from pairs of the whole corpus, copies weigh more."""
    docs = spark.read.parquet("/root/testdata/sf0.01/documents.parquet").where("text is not null").select("doc_id", "text")
    held = "crc32(cast(cast(doc_id as string) as binary)) % 7 = 2"
    rows = mixing.score_texts(docs, ~mixing.F.expr(held)).join(docs.select("doc_id", mixing.F.expr(held).alias("held")), "doc_id").collect()
    out = [r for r in rows if r.held]
    assert sum(r.score for r in out) > 0.97 * sum(r.base_score for r in out)
    assert sum(r.score for r in rows if not r.held) / sum(r.n_tokens for r in rows if not r.held) > sum(r.score for r in out) / sum(r.n_tokens for r in out)


def test_pair_counts_weigh_copies_and_round_down():
    v = np.zeros(7, mixing.exchange.NARROW)
    v["low"] = [5, 5, 5, 9, 9, 4, 2]
    ranks = np.zeros(7, mixing.exchange.RANK)
    ranks["rep"] = [1, 2, 0, 0, 0, 127, 10**6]
    notes = mixing.pair_counts(v, None, ranks)
    assert notes[:6].tolist() == [3, 3, 3, 0, 0, 127]
    assert 10**6 / 2**0.25 < mixing.COUNT_OF[notes[6]] <= 10**6
    assert len(mixing.pair_counts(v[:0], None, ranks[:0])) == 0


def test_runs_of_known_tokens():
    w = mixing.flat.Words([b"a b c d", b"", b"e f"])
    s = mixing.Stream(w, w.hashes(43))
    assert s.doc.tolist() == [0] * 5 + [1] + [2] * 3 and s.first.tolist() == [0, 5, 6]
    assert s.runs(np.array([True, True, False, True, True, True, True, True, False])).tolist() == [0, 1, 2, 0, 1, 0, 0, 1, 2]
    assert s.one[0] == s.one[5] == s.one[6] == s.two[1] == mixing.BEGINS and s.one[1] == s.h[0] and s.two[2] == s.h[0]


def test_mixing_probabilities_add_up():
    """Over all one-byte words and longer ones the spelled probabilities add up to no more than 1, and decisions of the head to 1."""
    m = mixing.Model(np.zeros(mixing.SLOTS, np.float16), np.zeros(mixing.SLOTS, np.uint8), np.zeros((mixing.GATES, 5), np.float32), np.full((mixing.GATES, mixing.STEPS), 0.5, np.float32))
    assert m.score([b"ab"])[0] == pytest.approx(-24)
    counts = np.zeros((3, mixing.HEAD + 1), np.int64)
    counts[:, :50] = np.random.default_rng(1).integers(0, 90, (3, 50))
    counts[:, mixing.HEAD] = 7
    assert np.exp2(mixing.head_odds(counts).astype(np.float64)).sum(1) == pytest.approx([1, 1, 1], abs=1e-4)


def test_sharding(docs, rows):
    got = sharding.assign_shards(docs, 4).collect()
    assert sorted((str(r.doc_id), r.size, r.text_crc32) for r in got) == sorted((str(i), len((t or "").encode()) + 1, zlib.crc32((t or "").encode())) for i, t, _ in rows)
    slots = defaultdict(list)
    for r in got:
        slots[r.shard].append(r.slot)
    assert all(sorted(s) == list(range(len(s))) for s in slots.values())
    pieces = [(c, 0, 1, 100) for c in range(0, 65536, 16)]
    a, b = ({(c, s): shard for c, s, shard, _ in sharding.place(pieces, n, 0.05)} for n in (8, 9))
    assert sum(a[k] != b[k] for k in a) < 0.35 * len(a)  # limited movement
    assert max(Counter(a.values()).values()) <= 1.05 * len(a) / 8


def test_sharding_keeps_groups_whole_but_those_that_overflow(spark):
    rows = [(k, "common text of a third of all rows") for k in range(600)] + [(1000 + k, f"text {k // 4} " + "word " * (k // 4 % 50)) for k in range(1200)] + [(None, None)] * 3
    got = sharding.assign_shards(spark.createDataFrame(rows, "doc_id long, text string"), 4).collect()
    where, sizes = defaultdict(set), Counter()
    for r in got:
        where[r.text_crc32].add(r.shard)
        sizes[r.shard] += r.size
    assert len(got) == len(rows) and max(sizes.values()) - min(sizes.values()) < 0.02 * sum(sizes.values())
    assert all(len(s) == 1 for c, s in where.items() if c != zlib.crc32(b"common text of a third of all rows"))


def test_sharding_moves_little_with_the_slack_of_the_query():
    pieces = [(c, 0, 1, 100) for c in range(0, 65536, 16)]
    a, b = ({(c, s): shard for c, s, shard, _ in sharding.place(pieces, n, 0.0005)} for n in (8, 9))
    assert 1 / 9 - 0.02 < sum(a[k] != b[k] for k in a) / len(a) < 0.45


def test_leaks(spark, docs):
    d = spark.createDataFrame([(1, "In 2019 Anna bought 12 apples and 5 kg of rice, then Anna gave 12 apples to Bert before noon today."), (2, "nothing at all"), (3, None), (None, "In 2019 Anna bought 12 apples and 5 kg of rice, then Anna gave 12 apples to Bert before noon today.")], "doc_id long, text string")
    items = spark.createDataFrame([(7, "In 1999 Carl bought 30 apples and 8 kg of rice, then Carl gave 30 apples to Dora before noon today."), (8, "In 1999 Carl bought 30 apples and 8 kg of rice, then Carl gave 31 apples to Dora before noon today."), (9, None), (10, "too short")], "item_id long, text string")
    got = decontam.find_leaks(d, items).collect()
    assert sorted((str(r.doc_id), r.item_id, r.exact) for r in got) == [("1", 7, False), ("None", 7, False)]
    assert decontam.find_leaks(docs, items.limit(0)).count() == 0 and decontam.find_leaks(d.limit(0), items).count() == 0


def test_leaks_with_names_at_sentence_starts(spark):
    d = spark.createDataFrame([(1, "Sue has 9 apples. Sue buys 4 more. Sue eats 6. How many are left?"), (2, "tom has 9 apples. tom buys 4 more. tom eats 6. how many are left?"), (3, "Sue has 9 apples. Ann buys 4 more. Bob eats 6. How many were lost?"), (4, 'He said: "Sue (Ann) has 9 apples." "Sue (Ann) buys 4 more." "Sue (Ann) eats 6."')], "doc_id long, text string")
    items = spark.createDataFrame([(7, "Tom has 5 apples. Tom buys 3 more. Tom eats 2. How many are left?"), (8, 'She said: "Tom (Bob) has 5 apples." "Tom (Bob) buys 3 more." "Tom (Bob) eats 2."')], "item_id long, text string")
    got = {(r.doc_id, r.item_id): r.coverage for r in decontam.find_leaks(d, items).collect()}
    assert set(got) == {(1, 7), (2, 7), (4, 8)} and got[1, 7] == got[2, 7] == got[4, 8] == 1


def test_leaks_of_short_items_and_short_runs(spark):
    question, run = "Which planet in our solar system has the most moons", "all eight of these words are a leak"
    d = [(k, "x " * k + question + " y") for k in range(4)] + [(10 + k, "x " * k + run + " y") for k in range(4)] + [(20, "so, Who wrote it? yes"), (21, "tom has 9 apples"), (22, "it is 1999"), (23, run.rsplit(" ", 1)[0])]
    items = [(1, question), (2, run + " of a longer item here"), (3, "Who wrote it"), (4, "tom has 5 apples"), (5, "2000"), (6, ""), (7, "1999"), (8, run.rsplit(" ", 1)[0] + " x")]
    got = {(r.doc_id, r.item_id) for r in decontam.find_leaks(spark.createDataFrame(d, "doc_id long, text string"), spark.createDataFrame(items, "item_id long, text string")).collect()}
    assert got == {(k, 1) for k in range(4)} | {(10 + k, 2) for k in range(4)} | {(20, 3), (21, 4), (22, 7)}


@pytest.mark.parametrize("rows", [decontam.BROADCAST_ROWS, 0])
def test_leaks_with_other_word_counts(spark, monkeypatch, rows):
    monkeypatch.setattr(decontam, "BROADCAST_ROWS", rows)
    w = [f"w{chr(97 + k // 26)}{chr(97 + k % 26)}" for k in range(36)]
    text = lambda *x: " ".join(x)
    items = [(1, text(*w[:12], "Boston", *w[12:24], "ends", *w[24:])), (3, text(*w[:12], "New York", *w[12:24], "ends", *w[24:])), (2, text("we mix 5 kg with 30 g and then 7 km", "on 2 m and 4 kg or 3 cm"))]
    d = [(1, text(*w[:12], "New York", *w[12:24], "really ends", *w[24:])), (2, "we mix 6kg with 40g and then 8km on 3m and 9kg or 1cm"), (3, text(*w[:12])), (4, text(*w[:12], *["x"] * 90, *w[24:])), (None, text(*w[24:], "and", *w[:12])), (5, None), (6, text(*w[:12], "Boston", *w[12:24], "really ends", *w[24:]))]
    got = {(r.doc_id, r.item_id): r for r in decontam.find_leaks(spark.createDataFrame(d, "doc_id long, text string"), spark.createDataFrame(items, "item_id long, text string")).collect()}
    assert set(got) == {(1, 1), (1, 3), (2, 2), (None, 1), (None, 3), (6, 1), (6, 3)} and not any(r.exact for r in got.values())
    assert got[1, 1].n_words == got[1, 1].n_matched == 38 and got[6, 3].n_words == got[6, 3].n_matched == 39 and got[6, 3].n_slots == 1 and got[2, 2].coverage == 1 and got[2, 2].n_words == 20 and got[None, 1].n_matched == 24


def test_nearest(spark):
    rng = np.random.default_rng(3)
    x = rng.normal(size=(900, 16))
    x[100:300] = x[100]  # one common vector
    rows = [(k, v.tolist()) for k, v in enumerate(x)] + [(2000, None), (2050, [0.0] * 16), (2100, [float("nan")] + [1.0] * 15), (None, x[0].tolist())]
    got = defaultdict(list)
    for r in graph_ann.nearest(spark.createDataFrame(rows, "vec_id long, embedding array<double>"), shard_rows=400).orderBy("query_id", "rank").collect():
        got[r.query_id].append((r.vec_id, r.score))
    unit = x / np.linalg.norm(x, axis=1, keepdims=True)
    hit = total = 0
    for q in range(0, 900, 50):
        s = unit @ unit[q]
        s[q] = -9
        best = np.lexsort((np.arange(900), -np.round(s, 12)))[:5]
        hit += len({i for i, _ in got[q]} & set(best.tolist()))
        total += 5
        assert all(abs(v - unit[i] @ unit[q]) < 1e-12 for i, v in got[q])
    assert set(got) == set(range(0, 900, 50)) and hit / total >= 0.9


def test_nearest_of_repeated_rows(spark):
    rng = np.random.default_rng(4)
    x = rng.normal(size=(120, 8))
    rows = [(k, v.tolist(), "e") for k, v in enumerate(x)] + [(50, x[50].tolist(), "again")] * 3 + [(7, x[7].tolist(), "again")] * 9
    rows += [(100, x[3].tolist(), "other vector")]
    got = graph_ann.nearest(spark.createDataFrame(rows, "vec_id long, embedding array<double>, id string")).collect()
    of = [r.vec_id for r in sorted((r for r in got if r.query_id == 50), key=lambda r: r.rank)]
    unit = x / np.linalg.norm(x, axis=1, keepdims=True)
    s = unit @ unit[50]
    s[50] = -9
    best = np.argsort(-s)[:5].tolist()
    assert of == best or 100 in of and len(set(of)) == 5
    assert Counter(r.query_id for r in got) == {0: 5, 50: 5, 100: 10}


def test_parse_dedup_of_planted_passages(spark, tmp_path):
    """Passages of known lengths in bytes: those of the length go whole, shorter ones stay, at 51 and 211 partitions alike."""
    r = random.Random(8)
    text = lambda n: "".join(r.choice("abcdefghij ") for _ in range(n))
    long, short, edge = text(900), text(390), "0" + text(398) + "1"
    rows = [(k, text(300 + k) + chr(65 + k) + "!" + p + "?" + chr(65 + k) + text(200)) for k, p in enumerate([long] * 3 + [short] * 3 + [edge] * 2)] + [(90, text(5000)), (91, None)]
    width = spark.conf.get("spark.sql.shuffle.partitions")
    try:
        for parts in ("51", "211"):
            spark.conf.set("spark.sql.shuffle.partitions", parts)
            got = {x.doc_id: x for x in parse_dedup.remove_repeated_bytes(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
            assert [got[k].n_removed for k in range(8)] == [902] * 3 + [0] * 3 + [402] * 2 and got[90].n_removed == got[91].n_removed == 0
            assert [got[k].n_spans for k in range(8)] == [1] * 3 + [0] * 3 + [1] * 2
    finally:
        spark.conf.set("spark.sql.shuffle.partitions", width)


def test_empty_tables(docs):
    none = docs.limit(0)
    path = bpe.vocabulary()
    assert bpe.digests(none, path).count() == 0
    assert token_store.look_up(none, *token_store.write_store(none, path)).count() == 0
    assert substring.remove_repeats(none).count() == parse_dedup.remove_repeated_bytes(none).count() == jaccard.near_duplicates(none).count() == 0
    assert sharding.assign_shards(none).count() == mixing.score_texts(none, none).count() == 0
    assert graph_ann.nearest(docs.sparkSession.createDataFrame([], "vec_id long, embedding array<float>")).count() == 0


def test_template_words_are_hashed_where_they_stand(spark, monkeypatch):
    from fixflow.llm import decontam

    plans, durable = {}, decontam.durable
    monkeypatch.setattr(decontam, "durable", lambda df, tag: plans.setdefault(tag, df._jdf.queryExecution().optimizedPlan().toString()) and durable(df, tag))
    text = "a quick test of ten plain words in one row"
    docs = spark.createDataFrame([(1, "so " + text), (2, "other"), (3, ""), (4, None)], "doc_id long, text string")
    out = decontam.find_leaks(docs, spark.createDataFrame([(9, text), (8, "other")], "item_id long, text string"))
    assert sorted((r.doc_id, r.item_id) for r in out.collect()) == [(1, 9), (2, 8)]
    assert "arrays_zip" not in plans["anchored"]  # no copies of all words for each place of a shingle


def test_written_tables_leave_no_shuffle_files(spark, tmp_path):
    import time

    from fixflow.llm import common

    disk = spark.sparkContext._jvm.org.apache.spark.SparkEnv.get().blockManager().diskBlockManager()

    def files():
        found = disk.getAllFiles()
        return {n for n in (found.apply(i).getName() for i in range(found.size())) if n.startswith("shuffle_")}

    before, named = files(), spark.conf.get(common.DROP_SHUFFLES)
    df = spark.range(1000).groupBy((mixing.F.col("id") % 7).alias("k")).count()
    out = common.durable(df, "few")
    for _ in range(20):
        left = files() - before
        if not left:
            break
        time.sleep(0.1)
    assert not left and out.count() == 7 and spark.conf.get(common.DROP_SHUFFLES) == named


def test_head_ranks_and_notes_are_found_without_searching():
    words = [b"%d" % k for k in range(5000)]
    head = mixing.Head([mixing.END, *words])
    head.hash[10:14] = head.hash[10] + np.arange(4, dtype=np.uint64)  # words that share a cell
    seen = np.concatenate([head.hash, head.hash + np.uint64(77), head.hash[:1]])
    assert head.ranks(seen).tolist() == [*head.rank.tolist(), *[mixing.HEAD] * len(head.hash), head.rank[0]] and head.most >= 4
    assert mixing.Head([mixing.END]).ranks(seen[:2]).tolist() == [mixing.HEAD] * 2
    texts = [b"a b c a b", b"", b"c " * 3000, b"b"]
    w = mixing.flat.Words(texts)
    t = mixing.Stream(w, w.hashes(43))
    note = (t.pairs() % np.uint64(251)).astype(np.uint8)
    sent = [note[a:b][np.argsort(mixing.exchange.bucket_of(t.pairs()[a:b], 51), kind="stable")].tobytes() for a, b in zip(t.first, t.ends + 1)]
    assert mixing._dealt(t, sent, 51).tolist() == note.tolist()
    with pytest.raises(ValueError):
        mixing._dealt(t, [sent[0][1:], sent[1] + b"0", *sent[2:]], 51)
    low = np.random.default_rng(1).integers(0, 50, 5000).astype(np.uint32)
    order, s = mixing.exchange.sorted_low(low)
    assert order.tolist() == np.argsort(low, kind="stable").tolist() and s.tolist() == sorted(low.tolist())


def test_learning_from_small_counts_equals_the_plain_odds():
    r = np.random.default_rng(2)
    n = r.integers(0, 65536, (500, 2)).astype(np.uint16)
    y = r.random(500) < 0.5
    n[np.arange(500), y.astype(int)] = np.maximum(1, n[np.arange(500), y.astype(int)])
    assert mixing.small_odds(n[:, 0].astype(np.int64), n[:, 1].astype(np.int64), y) == pytest.approx(mixing.odds(n, y), abs=1e-4)


def test_suffix_ranks_sort_open_groups_only(monkeypatch):
    r = np.random.default_rng(4)
    for symbols, lens in ((r.integers(0, 3, 400), [150, 1, 249]), (np.zeros(70, np.int64), [40, 30]), (r.permutation(500), [500]), (np.zeros(0, np.int64), [])):
        left = parse_dedup.left_of(np.array(lens, np.int64))
        tails = [tuple(symbols[i : i + n].tolist()) for i, n in enumerate(left.tolist())]
        place = {t: k for k, t in enumerate(sorted(set(tails)))}
        sizes, argsort = [], np.argsort
        monkeypatch.setattr(parse_dedup.np, "argsort", lambda x, *a, **k: sizes.append(len(x)) or argsort(x, *a, **k))
        rank = parse_dedup.doubled(symbols, left)
        monkeypatch.undo()
        assert np.unique(rank, return_inverse=True)[1].tolist() == [place[t] for t in tails] and (rank >= 1).all()
        assert len(place) < 500 or sizes and set(sizes[1:]) <= {0, 500} and sum(x > 0 for x in sizes) <= 2  # suffixes that are alone are sorted once
