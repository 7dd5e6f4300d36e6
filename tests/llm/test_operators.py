"""The operators against brute force on small tables, and their edge cases."""

import collections
import hashlib
import re
import struct
import zlib

import pytest

from innersearch.llm import chat, decontam, langid, linededup, linefilter, mixing, pii, ringshard, sigtree, tokenids
from innersearch.llm.registry import tokenizer_path

SCHEMA = "doc_id long, text string, lang string, source string, n_chars long, size long, part int"
LONG = " ".join(f"word{i % 997} tok{i % 13}." for i in range(20_000))
PASSAGE = " ".join(f"shared{i}" for i in range(60)) + "."
FIX = [
    (1, "The quick brown fox jumps over the lazy dog and runs away from it all day.", "en", "a"),
    (2, "The quick brown fox jumps over the lazy dog and runs away from it all day.", "en", "a"),
    (2, "The quick brown fox jumps over the lazy dog and runs away from it all day.", "en", "a"),
    (3, None, None, None),
    (4, "", "", ""),
    (5, " \n\t ", "en", "b"),
    (6, LONG, "en", "b"),
    (7, f"Intro line one.\n{PASSAGE}\nEnd.", "en", "c"),
    (8, f"Another start.\n\n{PASSAGE}\nTail of it.", "en", "c"),
    (9, "x", "fr", None),
    (10, "Mail me.at@host-1.example.org or +1 (555) 123-4567, ip 10.0.0.300 10.0.0.30, card 4111 1111 1111 1111.", "en", "a"),
    (None, "no id here", "de", "a"),
    (11, "été ÉTÉ naïve größte 日本語 <|endoftext|> İstanbul ΣΑΣ don't WE'LL 12345 ½  x y", "fr", "d"),
]
ROWS = [(i, t, la, so, None if t is None else len(t), 7, 1) for i, t, la, so in FIX]


@pytest.fixture(scope="module")
def docs(spark):
    return spark.createDataFrame(ROWS, SCHEMA).repartition(3)


@pytest.fixture(scope="module")
def empty(spark):
    return spark.createDataFrame([], SCHEMA)


def test_pii(docs, empty):
    assert pii.pii_digest(empty).count() == 0
    rows = {r["doc_id"]: r for r in pii.pii_digest(docs).collect()}
    r = rows[10]
    assert (r["n_email"], r["n_ip"], r["n_card"], r["n_phone"]) == (1, 1, 1, 1)
    text = FIX[10][1]
    spans = [s.split(":") for s in r["spans"].split(",")]
    assert {(k, text[int(a) : int(b)]) for k, a, b in spans} >= {("email", "me.at@host-1.example.org"), ("phone", "+1 (555) 123-4567"), ("ip", "10.0.0.30"), ("card", "4111 1111 1111 1111")}
    assert rows[3]["spans"] == rows[4]["spans"] == rows[6]["spans"] == ""
    clean = {r["doc_id"]: r["text"] for r in pii.redact(docs).collect()}
    assert "<email>" in clean[10] and "4111" not in clean[10] and clean[3] is None and clean[1] == FIX[0][1]


def test_pii_field_adds_local_numbers():
    field = pii.trained_field()
    text = "Please call (555) 123-4567 or write. In 1999 there were 12 of 300 left (5)."
    (base, every), = pii.all_spans(field, [text])
    assert base == [] and every == [(12, 26, "phone")]
    held = pii.labelled_table(200, seed=99)
    got = field.decode([(w, left, right) for w, _, left, right in held])
    pairs = [(a, b) for g, (_, y, _, _) in zip(got, held, strict=True) for a, b in zip(g, y, strict=True)]
    assert sum(a == b for a, b in pairs) / len(pairs) > 0.9


def test_endless_word_is_linear():
    assert pii.base_spans("a" * 300_000 + "@") == [] and pii.base_spans("1" * 300_000) == []


def test_chat(spark):
    schema = "conv_id long, turn long, role string, text string, conv string"
    text = "a\\b <|im_end|>\n<|im_sep|> <\\| \\s \\n"
    rows = [(1, 2, "assistant", text, "x"), (1, 1, "user", None, "x"), (1, 3, "assistant", "", "x"), (1, 3, "assistant", "", "x"), (2, None, None, "hi\n", "x"), (2, 0, "as\nsistant", "q", "x")]
    turns = spark.createDataFrame(rows, schema)
    out = {r["conv_id"]: r for r in chat.chat_digest(chat.with_probe(turns)).collect()}
    want = [("user", ""), ("assistant", ""), ("assistant", ""), ("assistant", text)]
    order = [("user", ""), ("assistant", text), ("assistant", ""), ("assistant", "")]
    assert out[1]["n_turns"] == len(want)
    assert out[1]["turns_sha256"] == hashlib.sha256("".join(f"{r}\n{t}\n" for r, t in order).encode()).hexdigest()
    assert out[1]["loss_sha256"] == hashlib.sha256(text.encode()).hexdigest() and out[1]["loss_chars"] == len(text)
    assert out[2]["n_turns"] == 2 and out[2]["loss_chars"] == 0
    assert out[-1]["n_turns"] == 2 and out[-1]["loss_chars"] == len("<|im_end|><|im_start|>assistant ok")
    assert chat.chat_digest(spark.createDataFrame([], schema)).count() == 0


def test_language(docs, empty, spark, sf_dir):
    assert langid.language_digest(empty).count() == 0
    small = {r["doc_id"]: r for r in langid.language_digest(docs).collect()}
    assert small[3]["lang_pred"] == small[4]["lang_pred"] == small[5]["lang_pred"] == "und" and small[3]["score"] == 0
    table = spark.read.parquet(f"{sf_dir}/documents.parquet")
    got = langid.language_digest(table).join(table.select("doc_id", "lang"), "doc_id").where("held_out and lang is not null")
    assert got.where("lang_pred = lang").count() >= 0.95 * got.count()
    assert got.where("score < 0 or score > 1").count() == 0


def test_rare_languages_are_learned(spark):
    """Three rows of one language among 70,000 of another."""
    rows = spark.range(70_000).selectExpr("id AS doc_id", "concat('the cat number ', id, ' sat on the mat') AS text", "'en' AS lang")
    rare = spark.createDataFrame([(-1 - i, f"zwiebel {i} knusprig gebraten", "de") for i in range(3)], "doc_id long, text string, lang string")
    total = langid.train(rows.unionByName(rare))
    few = langid.train(rows.limit(10).unionByName(rare))
    assert total.names == ["de", "en"] and abs(total.vectors[0] - few.vectors[0]).max() < 1e-3


def test_language_table_equals_vectors():
    p = langid.Profiles(["a", "b"], {"a": langid.gram_counts("the cat sat on the mat"), "b": langid.gram_counts("der Hund bellt laut heute")})
    text = "the dog on the mat"
    v = langid.exact_vector(text, p.letters)
    unit = p.vectors / ((p.vectors**2).sum(1, keepdims=True) ** 0.5)
    assert abs(p.table[langid.grams_of(text)].sum(0) - unit @ v).max() < 1e-2
    names, scores = p.predict([text])
    assert names == ["a"] and abs(scores[0] - (unit @ v).max() / (v @ v) ** 0.5) < 0.1


def test_tokens_equal_the_tokenizer(spark, docs, empty):
    from tokenizers import Tokenizer

    tok = Tokenizer.from_file(tokenizer_path())
    assert tokenids.token_digest(spark, empty, tokenizer_path()).count() == 0
    rows = tokenids.token_digest(spark, docs, tokenizer_path()).orderBy("start").collect()
    start = 0
    for r, (i, t) in zip(rows, sorted(((i, t or "") for i, t, *_ in FIX), key=lambda x: (x[0] is not None, x[0] or 0, x[1])), strict=True):
        ids = [*tok.encode(t, add_special_tokens=False).ids, 2]
        assert (r["doc_id"], r["start"], r["n_tokens"], r["ids_crc32"]) == (i, start, len(ids), zlib.crc32(struct.pack(f"<{len(ids)}I", *ids)))
        start += len(ids)


@pytest.mark.parametrize("kind", ["byte", "bit"])
def test_planes_round_trip(kind):
    import numpy as np

    for n in (0, 1, 7, 16_384, 40_001):
        ids = np.random.default_rng(n).integers(0, 2**32, n, np.uint64).astype("<u4")
        sizes, payload = tokenids.pack_ids(ids, kind=kind)
        assert (tokenids.unpack_ids(sizes, payload, n, kind=kind) == ids).all()


def _words(t):
    return re.findall(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+", "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in t or ""))


@pytest.mark.parametrize("max_words", [decontam.MAX_WORDS, 30])
def test_decontamination(spark, empty, max_words):
    items = [(1, "one two three four five six seven eight nine ten eleven twelve"), (2, "Short item, here!"), (3, None), (4, "..."), (5, "two three four five six seven eight nine ten eleven x y"), (5, "again"), (10, "short item")]
    texts = ["zero ONE two three four five six seven eight nine ten eleven twelve more", "a short item here b short item", None, "", "again again", "one two three four five six seven eight nine", "nothing of it", "three four five six seven eight nine ten eleven twelve"]
    bench = spark.createDataFrame(items, "item_id long, text string")
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    found = {r["doc_id"]: r for r in decontam.annotate_hits(docs, bench, ["doc_id"], max_words=max_words).withColumn("hit", decontam.n_hit(decontam.F.col("__spans"))).collect()}
    wins = collections.defaultdict(set)
    for i, t in items:
        w = _words(t)
        for k in range(max(1, len(w) - 9)) if w else []:
            wins[tuple(w[k : k + 10])].add(str(i))
    for d, t in enumerate(texts):
        w, hit, names = _words(t), set(), set()
        for win, who in wins.items():
            for k in range(len(w) - len(win) + 1):
                if tuple(w[k : k + len(win)]) == win:
                    hit.update(range(k, k + len(win)))
                    names |= who
        assert (found[d]["__n_words"], found[d]["hit"], found[d]["__items"]) == (len(w), len(hit), sorted(names))
    kept = {r["doc_id"]: r["text"] for r in decontam.decontaminate(docs, bench, max_coverage=0.9).collect()}
    assert kept[0] == "zero  more" and kept[6] == "nothing of it" and 4 not in kept and kept[2] is None
    assert decontam.hit_digest(empty, bench).count() == 0
    assert decontam.hit_digest(docs, bench.limit(0)).where("contaminated").count() == 0


def _components(texts, k, num, den):
    sets = {}
    for i, t in texts:
        w = re.findall(r"[^\x20\x09-\x0D]+", "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in t or ""))
        sets[i] = {tuple(w[j : j + k]) for j in range(len(w) - k + 1)} if len(w) >= k else {tuple(w)} if w else set()
    up = {i: i for i in sets}

    def root(a):
        while up[a] != a:
            a = up[a]
        return a

    for a in sets:
        for b in sets:
            if a < b and sets[a] and sets[b]:
                both = len(sets[a] & sets[b])
                if den * both >= num * (len(sets[a]) + len(sets[b]) - both):
                    x, y = sorted((root(a), root(b)))
                    up[y] = x
    return {i: (len(sets[i]), root(i)) for i in sets}


@pytest.mark.parametrize("block", [1024, 6])
def test_signature_join(spark, docs, empty, block):
    import random

    r = random.Random(3)
    base = [[f"w{r.randint(0, 400)}" for _ in range(r.choice([4, 9, 12, 30, 120]))] for _ in range(12)]
    texts = []
    for b in base:
        for _ in range(8):
            v = list(b)
            for _ in range(r.choice([0, 0, 1, 1, 2, 4])):
                v[r.randrange(len(v))] = f"z{r.randint(0, 50)}"
            texts.append((len(texts), " ".join(v)))
    df = spark.createDataFrame(texts, "doc_id long, text string")
    for k, num in ((3, 90), (5, 80), (2, 60)):
        got = {x["doc_id"]: (x["n_shingles"], x["component_id"]) for x in sigtree.similar_components(df, k, num, 100, block).collect()}
        assert got == _components(texts, k, num, 100)
    if block > 6:
        assert sigtree.similar_components(empty).count() == 0
        got = sorted((x["doc_id"] or 0, x["n_shingles"], x["component_id"]) for x in sigtree.similar_components(docs).collect())
        assert len(got) == len(FIX) and [g for g in got if g[0] == 2] == [(2, 14, 1)] * 2 and (4, 0, 4) in got
        kept = sigtree.keep_one(docs)
        assert kept.columns == docs.columns and kept.where("doc_id = 2").count() == 0 and kept.where("doc_id = 1").count() == 1


def _null_id_near_pairs():
    """Triples X (no doc_id), Y, Z: Y and Z are X with its last and its first word changed, in every order of node ids."""
    rows, orders = [], set()
    for g in range(24):
        x = [f"g{g}w{i}" for i in range(120)]
        texts = [" ".join(w) for w in (x, [*x[:-1], "other"], ["other", *x[1:]])]
        nodes = [sigtree._prints(s)[2] for s in sigtree.shingle_sets([t.encode() for t in texts])]
        orders.add(tuple(sorted(range(3), key=nodes.__getitem__)))
        rows += zip((None, 2 * g, 2 * g + 1), texts, strict=True)
    assert len(orders) == 6
    return rows


@pytest.mark.parametrize("k, num", [(3, 90), (5, 80)])
def test_rows_without_an_id_break_no_link(spark, k, num):
    df = spark.createDataFrame(_null_id_near_pairs(), "doc_id long, text string")
    got = {r["doc_id"]: r["component_id"] for r in sigtree.similar_components(df, k, num, 100).collect() if r["doc_id"] is not None}
    assert got == {i: i - i % 2 for i in range(48)}


def test_key_groups_of_long_runs(monkeypatch):
    """Runs of equal keys that cross batches; a run above RUN becomes pairs with its least id."""
    import numpy as np
    import pyarrow as pa

    class Rows:
        def repartition(self, *_):
            return self

        sortWithinPartitions = distinct = repartition

        def mapInArrow(self, f, _):
            self.f = f
            return self

    monkeypatch.setattr(sigtree, "RUN", 3)
    runs = {1: range(10), 2: [5, 6], 3: [7], 4: range(3), 5: [3, 3], 9: [0, 8, 8]}
    k = np.array([key for key, ids in runs.items() for _ in ids], np.int64)
    v = np.array([i for ids in runs.values() for i in ids], np.int64)
    for size in (1, 2, 4, 100):
        batches = [pa.RecordBatch.from_arrays([pa.array(x[i : i + size]) for x in (k, v, 0 * v)], names=["key", "id", "to"]) for i in range(0, len(k), size)]
        groups = collections.defaultdict(set)
        for b in sigtree.key_groups(Rows()).f(iter(batches)):
            for g, i, sure in zip(*[c.to_pylist() for c in b.columns], strict=True):
                groups[g, sure].add(i)
        got = {(frozenset(m), sure) for (_, sure), m in groups.items()}
        assert {(frozenset(m), False) for m in ([5, 6], [0, 1, 2], [0, 8])} <= got
        assert all((frozenset([0, i]), True) in got for i in range(1, 10)) or (frozenset(range(10)), False) in got


def test_line_runs(docs, empty):
    assert linededup.copy_digest(empty).count() == 0
    rows = collections.defaultdict(list)
    for r in linededup.copy_digest(docs).collect():
        rows[r["doc_id"]].append(r)
    assert rows[7][0]["deleted"] == "" and rows[8][0]["deleted"] == "2" and rows[8][0]["n_deleted"] == 1
    assert [r["n_deleted"] for r in rows[2]] == [0, 0] and rows[3][0]["n_lines"] == 0
    left = {r["doc_id"]: r["text"] for r in linededup.drop_copies(docs).collect()}
    assert left[8] == "Another start.\n\nTail of it." and left[7] == FIX[7][1] and left[3] is None


def test_line_runs_brute_force(spark):
    import random

    r = random.Random(5)
    lines = [" ".join(f"l{i}w{j}" for j in range(r.choice([1, 2, 5, 12]))) for i in range(25)]
    texts = []
    for i in range(60):
        at = r.randrange(20)
        texts.append((i, "\n".join([f"own {i}", *lines[at : at + r.randrange(1, 6)], "" if i % 3 else f"mid {i}", *r.sample(lines, 2)])))
    df = spark.createDataFrame(texts, "doc_id long, text string")
    for least in (4, 10, 30):
        got = {x["doc_id"]: x["deleted"] for x in linededup.copy_digest(df, least).collect()}
        seqs = {i: [(k, x, len(x.split())) for k, x in enumerate(t.split("\n")) if x] for i, t in texts}
        first, gone = {}, collections.defaultdict(set)
        for i, q in seqs.items():
            for a in range(len(q)):
                for b in range(a, len(q)):
                    if sum(x[2] for x in q[a : b + 1]) >= least:
                        if first.setdefault(tuple(x[1] for x in q[a : b + 1]), (i, a)) < (i, a):
                            gone[i].update(range(q[a][0], q[b][0] + 1))
        assert got == {i: ",".join(map(str, sorted(gone[i]))) for i in seqs}


def test_line_filter(docs, empty):
    assert linefilter.line_digest(empty).count() == 0
    rows = {r["doc_id"]: r for r in linefilter.line_digest(docs).collect()}
    for i, t, *_ in FIX:
        w = re.findall(r"[^\x20\x09-\x0D]+", t or "")
        n = collections.Counter(tuple(w[k : k + 3]) for k in range(len(w) - 2))
        at = {p for k in range(len(w) - 2) if n[tuple(w[k : k + 3])] > 1 for p in (k, k + 1, k + 2)}
        assert (rows[i]["n_words"], rows[i]["word_chars"], rows[i]["n_repeat_words"]) == (len(w), sum(map(len, w)), len(at))
    body = "\n".join(["Home | About | Contact | Help", *[" ".join(f"word{i}x{j}" for j in range(10)) + "." for i in range(10)], "Copyright (c) 2020 All rights reserved."])
    df = docs.sparkSession.createDataFrame([(1, body, "x"), (2, "### *** $$$ " * 40, "x")], "doc_id long, text string, size string")
    out = {r["doc_id"]: r["text"] for r in linefilter.clean(df).collect()}
    assert 2 not in out and "Home |" not in out[1] and "Copyright" not in out[1] and out[1].count("\n") == 9


def test_mix(docs, empty, spark, sf_dir):
    assert mixing.mix_digest(empty).count() == 0 and mixing.mixed_rows(empty).count() == 0
    small = mixing.mix_digest(docs).collect()
    assert len(small) == len(FIX) and all(0 <= r["taken"] <= 2 * r["size"] for r in small)
    table = spark.read.parquet(f"{sf_dir}/documents.parquet")
    rows = mixing.mix_digest(table).collect()
    source = {r["doc_id"]: r["source"] for r in table.select("doc_id", "source").collect()}
    size, want, took = collections.Counter(), {}, collections.Counter()
    for r in rows:
        s = source[r["doc_id"]]
        size[s] += r["size"]
        want[s] = r["target"]
        took[s] += r["taken"]
    left, open_ = 1.5 * sum(size.values()), sorted(size)
    weight = {s: (5, 2, 1)[i % 3] for i, s in enumerate(open_)}
    level = {}
    while open_:  # water filling by hand
        per = left / sum(weight[s] for s in open_)
        full = [s for s in open_ if per * weight[s] > 2 * size[s]]
        level |= {s: 2 * size[s] for s in full} or {s: per * weight[s] for s in open_}
        left -= sum(2 * size[s] for s in full)
        open_ = [s for s in open_ if s not in full] if full else []
    assert all(abs(level[s] - want[s]) < 1e-6 * max(1, level[s]) and abs(took[s] - want[s]) <= 1 for s in size)
    assert sorted(mixing.mix_digest(table).collect()) == sorted(rows)
    words = mixing.mixed_rows(table).select(mixing.n_words(mixing.F.col("text")).alias("n")).agg(mixing.F.sum("n")).first()[0]
    assert words == sum(took.values())


def test_shards(docs, empty, spark, sf_dir):
    assert ringshard.law_digest(empty).count() == 0
    assert ringshard.law_digest(docs).count() == len(FIX)
    table = spark.read.parquet(f"{sf_dir}/documents.parquet")
    rows = ringshard.law_digest(table).collect()
    load, slots = collections.Counter(), collections.defaultdict(list)
    for r in rows:
        load[r["shard"]] += r["size"]
        slots[r["shard"]].append(r["slot"])
    assert all(sorted(s) == list(range(len(s))) for s in slots.values())
    mean = sum(load.values()) / 16
    assert len(rows) == table.count() and max(load.values()) - mean <= max(r["size"] for r in rows)
    assert sorted(ringshard.law_digest(table).collect()) == sorted(rows)
    fewer = {r["doc_id"]: r["shard"] for r in ringshard.shard(table, shards=15).collect()}
    stay = sum(fewer[r["doc_id"]] == r["shard"] for r in rows) / len(rows)
    assert stay > 0.5  # most keys keep their shard when one is added


def test_a_shard_more_moves_little_more_than_its_share(spark):
    table = spark.read.parquet("/root/testdata/sf0.01/documents.parquet")
    before, after = ({r["doc_id"]: r["shard"] for r in ringshard.shard(table, shards=n).collect()} for n in (16, 17))
    moved = sum(before[i] != after[i] for i in before) / len(before)
    assert 0.5 / 17 < moved < 2 / 17


@pytest.mark.parametrize("k, num", [(3, 90), (5, 80)])
def test_rows_of_one_id_keep_their_own_component(spark, k, num):
    a, b = [f"a{i}" for i in range(60)], [f"b{i}" for i in range(60)]
    rows = [(5, " ".join(a)), (5, " ".join(b)), (3, " ".join([*a[:-1], "z"])), (2, " ".join(b)), (None, "x y z"), (None, "x y q"), (7, "u v w"), (7, "u v w")]
    df = spark.createDataFrame(rows, "doc_id long, text string")
    got = sorted((r["doc_id"], r["component_id"]) for r in sigtree.similar_components(df, k, num, 100).collect() if r["doc_id"] is not None)
    assert got == [(2, 2), (3, 3), (5, 2), (5, 3), (7, 7), (7, 7)]
    kept = sigtree.keep_one(df, words=k, num=num, den=100).collect()
    assert sorted((r["doc_id"] or 0, r["text"]) for r in kept) == sorted([(0, "x y z"), (0, "x y q"), (2, rows[3][1]), (3, rows[2][1]), (7, "u v w")])


def test_common_shingles_and_the_prefix_order(spark):
    """A passage of all rows is known as common and comes last; counts are exact while a task holds them."""
    import numpy as np

    shared = " ".join(f"s{i}" for i in range(30))
    df = spark.createDataFrame([(i, f"{shared} " + " ".join(f"o{i}x{j}" for j in range(30))) for i in range(40)], "doc_id long, text string").repartition(1)
    order = sigtree.common_shingles(df, 5)
    want = sigtree.shingle_sets([shared.encode()], 5)[0]
    assert sorted(order.hashes) == sorted(want) and not len(order.hot)
    s = sigtree.shingle_sets([df.first()["text"].encode()], 5)[0]
    assert not np.isin(order.prefix(s, 80, 100).view(np.uint64), want).any() and len(order.prefix(s, 80, 100)) == len(s) - -(-len(s) * 80 // 100) + 1
    k, n = sigtree._merged(np.zeros(0, np.uint64), np.zeros(0, np.int64), [np.repeat(np.arange(100, dtype=np.uint64), [50] * 2 + [1] * 98)], 10)
    assert set(k.tolist()) == {0, 1}


def test_hot_keys_are_chained_before_the_shuffle():
    import numpy as np

    keys = [np.array([1, 2, 3]), np.array([1, 2]), np.array([1, 9])]
    for hot, want in ((None, {(1, 5, 0), (2, 5, 0), (3, 5, 0), (9, 8, 0), ("p", 5, 7), ("p", 5, 8)}), (np.array([1]), {(1, 5, 0), (2, 5, 0), (2, 7, 0), (3, 5, 0), (9, 8, 0), ("p", 5, 7), ("p", 5, 8)})):
        k, v, to = sigtree._sent(keys, [5, 7, 8], hot)
        assert {("p" if c else a, b, c) for a, b, c in zip(k.tolist(), v.tolist(), to.tolist(), strict=True)} == want and len(k) == len(want)


CLASH = ["g_id", "g_lines", "epochs", "target", "p_source", "__take", "take", "row", "n", "mix", "__gone", "__text", "__n0", "__spans", "__items", "__words", "__line", "__lines", "__mix", "__n", "__N_WORDS", "__cut", "__th", "__lang_pred", "c0", "c1", "th", "line", "words"]


def test_clashing_names(spark):
    from pyspark.sql import functions as F

    rows = spark.createDataFrame([(i, f"line one of {i} goes on.\nthe cat sat on the mat " + " ".join(f"w{i}x{j}" for j in range(60)) + ".", "en", "ab"[i % 2]) for i in range(6)] + [(9, None, None, None)], "doc_id long, text string, lang string, source string")
    wide = rows.select("*", *[F.concat(F.lit(c), F.col("doc_id").cast("string")).alias(c) for c in CLASH])
    bench = spark.createDataFrame([("i1", "cat sat on the mat")], "item_id string, text string")
    profiles = langid.train(rows)
    steps = {
        "drop_copies": lambda d: linededup.drop_copies(d, 5),
        "clean": linefilter.clean,
        "mixed_rows": mixing.mixed_rows,
        "keep_one": lambda d: sigtree.keep_one(d, words=5, num=80, den=100),
        "decontaminate": lambda d: decontam.decontaminate(d, bench),
        "keep_languages": lambda d: langid.keep_languages(d, profiles, least=0.01),
        "redact": pii.redact,
    }
    for name, step in steps.items():
        got, plain = step(wide), step(rows)
        assert got.columns == wide.columns, name
        key = lambda r: str((r["doc_id"], r["text"]))
        assert sorted(map(key, got.collect())) == sorted(map(key, plain.collect())), name
        assert got.where(" OR ".join(f"`{c}` != concat('{c}', doc_id)" for c in CLASH)).count() == 0, name


def test_first_words_keep_white_space(spark):
    from pyspark.sql import functions as F

    text = " \n a\n\nb\tc  d\n"
    df = spark.createDataFrame([(text, n) for n in (1, 2, 3, 4)], "t string, n long")
    got = {r["n"]: r["x"] for r in df.select("n", mixing.first_words(F.col("t"), F.col("n")).alias("x")).collect()}
    assert got == {1: " \n a", 2: " \n a\n\nb", 3: " \n a\n\nb\tc", 4: " \n a\n\nb\tc  d"}


def test_encoder_caches_are_bounded():
    coder = tokenids.WordEncoder(tokenizer_path(), 100_000)
    plain = tokenids.WordEncoder(tokenizer_path())
    texts = [" ".join(f"w{(i * 7 + j * j) % 5000}ab" for j in range(100)).encode() for i in range(100)] + [b"x" * 300_000]
    assert [coder.encode(t) for t in texts] == [plain.encode(t) for t in texts]
    assert coder.words.held <= coder.words.half and len(coder.words.now) + len(coder.words.old) < 100_000 // tokenids.Cache.HEAD
    long = (" ".join(f"tok{i}" for i in range(300_000)) + " " + "y" * 2_000_000 + " end").encode()
    assert plain.encode(long) == plain._encoded(long)


def test_long_items_are_divided(spark):
    """One item of more words than an automaton may hold keeps all its windows."""
    words = [f"w{i}" for i in range(300)]
    bench = spark.createDataFrame([("big", " ".join(words)), ("other", "p q r")], "item_id string, text string")
    docs = spark.createDataFrame([(i, " ".join(["a", *words[i : i + 12], "z"])) for i in range(0, 288, 7)], "doc_id long, text string")
    got = decontam.annotate_hits(docs, bench, ["doc_id"], max_words=40).collect()
    assert all(r["__spans"] == [1, 13] and r["__items"] == ["big"] for r in got) and len(got) == docs.count()
    assert sum(1 for _ in decontam.automata(bench, max_words=40)) > 5


def test_encoder_holds_a_word_once():
    """Words of one piece take no second entry, so a cache holds as many as its bytes allow; ids are the tokenizer's own."""
    import numpy as np
    from tokenizers import Tokenizer

    coder, full = tokenids.WordEncoder(tokenizer_path(), 1_000_000), Tokenizer.from_file(tokenizer_path())
    words = ["".join(chr(97 + i * 7**j // 5**j % 26) for j in range(8)) + chr(97 + i % 26) + chr(97 + i // 26 % 26) + chr(97 + i // 676) for i in range(3700)]
    coder.encode(" ".join(words).encode())
    assert all(w.encode() in coder.words.now or w.encode() in coder.words.old for w in words)
    for text in ("kalo Kalo, KALO kalo's größe Größe GRÖSSE 's ''s x''s 12a <|x|> ×÷ ÿ ß, '", "' '' , ,, kalo,kalo"):
        want = [i for w in text.split() for i in full.encode(w, add_special_tokens=False).ids]
        assert np.frombuffer(coder.encode(text.encode()), "<u4").tolist() == want
        assert np.frombuffer(coder.encode(text.encode()), "<u4").tolist() == want
