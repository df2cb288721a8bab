"""Hard inputs of the text operators: repeated and null identifiers, colliding words, long paths and texts, clashing columns."""

import hashlib
import random
import re
import time
import zlib
from collections import Counter

import numpy as np
import pytest

import corpus_pipeline
from provgraph.llm import chat_format, decontaminate, exact_dedup, language_id, line_dedup, ngram_join, packing, pii, substring_dedup, token_counts
from provgraph.llm.common import components, shared_dir
from provgraph.llm.queries import BYTE_PATTERN, TOKENIZERS

LOW = str.maketrans("ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")
WORD = re.compile("[^\x20\x09-\x0d]+")
DOCS = "doc_id long, text string, lang string, source string, n_chars long"


def base_spans(t):
    """Plain identifiers by the patterns as they are stated, one after the other."""
    out = []
    for m in re.finditer(r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+", t):
        out.append((m.start(), 0, m.end()))
    for m in re.finditer(r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)", t):
        if all(int(x) <= 255 for x in m.group().split(".")):
            out.append((m.start(), 1, m.end()))
    for m in re.finditer(r"[0-9]([\x20-]?[0-9])+", t):
        d = [int(c) for c in m.group() if c in "0123456789"]
        total = sum(x if k % 2 == 0 else sum(divmod(2 * x, 10)) for k, x in enumerate(reversed(d)))
        if 12 <= len(d) <= 19 and total % 10 == 0:
            out.append((m.start(), 2, m.end()))
    for m in re.finditer(r"\+[0-9][\x20().0-9-]+[0-9]", t):
        if 9 <= sum(c in "0123456789" for c in m.group()) <= 15:
            out.append((m.start(), 3, m.end()))
    return sorted(out)


def test_pii_base_by_brute_force(spark):
    rng = random.Random(8)
    parts = ["4111 1111 1111 1111", "4111-1111-1111-1112", "10.0.0.1", "1.2.3.4.5.6.7.8", "300.1.1.1", "a@b.co", "x@y", "@z.org", "+44 20 7946 0958", "+1", "(", "12", " ", "-", ".", "é", "one two three four", "at", "dot", "j@k.l.m.", "+123456789"]
    rows = [(i, "".join(rng.choice(parts) + rng.choice(["", " "]) for _ in range(rng.randint(0, 14)))) for i in range(400)] + [(900, None), (901, "")]
    names = ("email", "ip", "card", "phone")
    got = {r["doc_id"]: r for r in pii.find_pii(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    for i, t in rows:
        want = base_spans(t or "")
        text = ",".join(f"{names[k]}:{a}:{b}" for a, k, b in want)
        assert got[i]["base_sha256"] == hashlib.sha256(text.encode()).hexdigest(), t
        assert [got[i][f"n_{n}"] for n in names] == [sum(k == j for _, k, _ in want) for j in range(4)]
        assert set(filter(None, text.split(","))) <= set(got[i]["spans"].split(","))


@pytest.mark.parametrize(
    "text",
    ["one two three " + "1" * 10**6 + "x", "one two three" + " " * 10**6 + "x", "a" * 10**6 + " @", "@" * 10**6 + " dot x", "a at " * 200_000, "a dot " * 160_000 + "at x dot com", " " * 500_000 + "[" + " " * 500_000 + "at]"],
    ids=["digits", "spaces", "word", "signs", "ats", "dots", "bracket"],
)
def test_pii_time_grows_with_the_text(text):
    began = time.process_time()
    pii.added(text, pii.detect(text))
    assert time.process_time() - began < 8  # quadratic patterns took hours


def grams(text, orders=3):
    s = [c if c.isalpha() else " " for c in text.lower()]
    return {tuple(s[k : k + n]) for n in range(1, orders + 1) for k in range(len(s) - n + 1)}


def test_language_scores_equal_those_of_the_gram_matrix():
    rng = random.Random(2)
    syll = {"aa": ["ka", "lo", "mi"], "bb": ["ür", "lo", "ter"], "cc": ["mi", "el", "que"]}
    rows = [(y, " ".join("".join(rng.choice(syll[y]) for _ in range(3)) for _ in range(8))) for y in sorted(syll) for _ in range(20)]
    model = language_id.fit(rows, landmarks=30)
    sets = [grams(t) for _, t in rows]
    kernel = lambda a, b: len(a & b) / np.sqrt(len(a) * len(b))
    chosen = [j for y in sorted(syll) for j in [k for k, (z, _) in enumerate(rows) if z == y][::2]]
    gram = lambda xs: np.array([[kernel(x, sets[j]) for j in chosen] for x in xs])
    vals, vecs = np.linalg.eigh(gram([sets[j] for j in chosen]))
    good = vals > 1e-6 * vals.max()
    root = vecs[:, good] / np.sqrt(vals[good])
    phi, y = gram(sets) @ root, np.array([[float(z == lab) for lab in sorted(syll)] for z, _ in rows])
    w = np.linalg.solve(phi.T @ phi + 1e-2 * np.eye(phi.shape[1]), phi.T @ y)
    texts = ["kalomi ürter", "Quemi elel, LOKA 12", "terlo terter que"]
    s = np.exp(8 * (gram([grams(t) for t in texts]) @ root @ w).clip(-2, 2))
    want = (s / s.sum(1, keepdims=True)).max(1)
    got = language_id.predict(texts, model)
    assert [sorted(syll)[k] for k in s.argmax(1)] == [x for x, _ in got]
    assert np.allclose(want, [x for _, x in got], atol=2e-3)


def test_language_sample_is_bounded_and_scripts_differ(spark):
    same = [(None, "so ist das nun einmal", "de")] * 3000 + [(7, "こんにちは世界の皆さん", "ja")] * 500
    more = [(k, f"это предложение номер {'абвгд'[k % 5]}", "ru") for k in range(40)] + [(k, f"一些中文句子没有空格{'甲乙丙丁'[k % 4]}", "zh") for k in range(40, 80)]
    df = spark.createDataFrame(same + more, "doc_id long, text string, lang string")
    got = Counter(y for y, _ in language_id.sample(df, "lang", "text", "doc_id", 30, 3000))
    assert got["de"] == got["ja"] == 1 and got["ru"] == got["zh"] == 30
    model = language_id.fitted(df, per_label=30, landmarks=40)
    assert [x for x, _ in language_id.predict(["新的中文句子没有", "новое предложение", "世界のこんにちは"], model)] == ["zh", "ru", "ja"]


def test_identifiers_of_other_types(spark):
    rows = [(1, "a b"), (2, "a b"), (None, "a b"), (3, None)]
    df = spark.createDataFrame(rows, "doc_id int, text string")
    got = exact_dedup.exact_dedup(df)
    assert got.schema["keep_id"].dataType.simpleString() == "int" and {r["keep_id"] for r in got.collect()} == {2, 3}
    text = df.withColumn("doc_id", df.doc_id.cast("string"))
    for refused in (exact_dedup.exact_dedup, substring_dedup.remove_repeats):
        with pytest.raises(TypeError):
            refused(text)
    assert {r["component_id"] for r in ngram_join.ngram_components(text).collect()} == {"1", "3"}
    assert sorted(r["n_removed"] for r in line_dedup.remove_lines(text).collect()) == [0, 0, 1, 1]


def test_words_that_tie_in_the_sort_key_keep_their_order(monkeypatch):
    monkeypatch.setattr(line_dedup, "words", lambda data, lower: _colliding(data))
    x = line_dedup.Lines([b"a b a c", b"b a c", b"c a b b a"], np.zeros(line_dedup.CELLS, np.int64))
    assert x.size.tolist() == [3, 3, 3] and len(set(x.node.tolist())) == 1
    assert len({tuple(x.words[b : b + 3].tolist()) for b in x.begin}) == 1


def _colliding(data):
    at = [k for k, c in enumerate(data) if chr(c).isalpha()]
    h = np.array([{"a": 5, "b": 6, "c": 1 << 40}[chr(data[k])] for k in at], np.uint64)  # a and b agree in the leading 28 bits
    return h, np.array(at), np.array(at) + 1


def test_components_of_a_long_path(spark):
    n = 3000
    path = spark.range(n).selectExpr("id * 7919 % 3001 AS u", "(id + 1) * 7919 % 3001 AS v")
    got = components(path).collect()
    assert len(got) == n + 1 and {r["root"] for r in got} == {0}


def test_shared_folder_is_asked_for_on_a_cluster(spark):
    class Context:
        master, applicationId = "spark://host:7077", "x"

        def getConf(self):
            return {}

    class Session:
        sparkContext, conf = Context(), {}

    with pytest.raises(ValueError, match="checkpoint"):
        shared_dir(Session())


def test_hot_passages_cross_buffers(spark, monkeypatch):
    monkeypatch.setattr(substring_dedup._Exchange.__init__, "__defaults__", (40,))  # buffers of 40 entries
    passage = " ".join(f"w{k}" for k in range(30))
    rows = [(k, f"{'x' * (k % 3)} {passage[: 90 + k]} tail{k}") for k in (5, 3, 9, 1, 12, 7, 30, 22)] + [(8, passage), (8, passage)]
    df = spark.createDataFrame(rows, "doc_id long, text string").repartition(3)
    first, want = {}, Counter()
    for i, t in rows:
        w = WORD.findall(t)
        for k in range(len(w) - 12):
            first[tuple(w[k : k + 13])] = min(i, first.get(tuple(w[k : k + 13]), i))
    for i, t in rows:
        w = WORD.findall(t)
        gone = {j for k in range(len(w) - 12) if first[tuple(w[k : k + 13])] < i for j in range(k, k + 13)}
        want[i, len(w), len(gone)] += 1
    assert Counter((r["doc_id"], r["n_words"], r["n_removed"]) for r in substring_dedup.remove_repeats(df).collect()) == want


def test_hot_tokens_are_split(spark, monkeypatch):
    """Blocks in pieces, in the exchange and in the joins, give what whole ones give."""
    rng = random.Random(21)
    common = [f"w{k}" for k in range(24)]
    rows = []
    for k in range(70):
        w = list(common)
        for _ in range(rng.choice([1, 2, 3, 9])):
            w[rng.randrange(24)] = f"x{rng.randrange(40)}"
        rows.append((k, " ".join(w)))
    df = spark.createDataFrame(rows, "doc_id long, text string").repartition(3)
    monkeypatch.setattr(ngram_join.Outbox.__init__, "__defaults__", (60, 3))  # buffers of 60 entries, hot beyond 3
    monkeypatch.setattr(line_dedup.later_lines, "__defaults__", (5,))
    lines = [(i, frozenset(t.split())) for i, t in rows]
    gone = {i for i, x in lines if any(j < i and 100 * len(x & y) >= 75 * len(x | y) for j, y in lines)}
    assert {r["doc_id"] for r in line_dedup.remove_lines(df).filter("n_removed = 1").collect()} == gone and len(gone) > 20
    sets = {i: shingles(t) for i, t in rows}
    root = {i: i for i in sets}
    for i in sets:
        for j in sets:
            if j < i and 100 * len(sets[i] & sets[j]) >= 75 * len(sets[i] | sets[j]):
                root = {k: min(root[i], root[j]) if v in (root[i], root[j]) else v for k, v in root.items()}
    got = {r["doc_id"]: r["component_id"] for r in ngram_join.ngram_components(df, per_block=5).collect()}
    assert got == root


@pytest.mark.parametrize("bits", [4, 15, 16, 20, 24])
def test_exchange_keys_come_back(bits):
    import pyarrow as pa

    h = np.sort(np.random.Generator(np.random.PCG64(1)).integers(0, 2**64 - 1, 200, dtype=np.uint64))
    box = substring_dedup._Exchange(bits, True)
    box.add(h, np.arange(200), np.zeros(200, np.uint32))
    t = pa.Table.from_batches([box.take()])
    got = np.concatenate([substring_dedup._keys(t.slice(k, 1), bits) for k in range(t.num_rows)])
    assert set(got.tolist()) == set(substring_dedup._full(h, bits).tolist()) and len(set(got.tolist())) == 200


def test_cover_is_the_union():
    rng = random.Random(3)
    for _ in range(300):
        at = np.array(sorted(rng.sample(range(80), rng.randint(1, 40))))
        words = {j for a in at.tolist() for j in range(a, a + 13)}
        chosen = substring_dedup._cover(at, 13)
        assert set(chosen) <= set(at.tolist()) and {j for a in chosen for j in range(a, a + 13)} == words
        assert len(chosen) <= len(words) // 7 + 1


def test_long_texts_and_clashing_columns(spark):
    rng = random.Random(9)
    long = " ".join(rng.choice("ab cd ef gh ij".split()) + str(rng.randint(0, 9999)) for _ in range(400_000))
    rows = [(1, long, "xx", "s", 0, 1, 2, 3), (2, long + " end", "xx", "s", 0, 1, 2, 3), (3, "x" * 2_000_000, None, None, None, 1, 2, 3)]
    df = spark.createDataFrame(rows, DOCS + ", i long, t long, key long")
    assert [r["component_id"] for r in ngram_join.ngram_components(df).orderBy("doc_id").collect()] == [1, 1, 3]
    assert [r["n_removed"] for r in line_dedup.remove_lines(df).orderBy("doc_id").collect()] == [0, 1, 0]
    assert [r["n_removed"] for r in substring_dedup.remove_repeats(df).orderBy("doc_id").collect()] == [0, 400_000, 0]
    assert [r["held_out"] for r in language_id.language_id(df).orderBy("doc_id").collect()] == [zlib.crc32(str(k).encode()) % 3 == 1 for k in (1, 2, 3)]
    assert pii.find_pii(df).count() == 3
    assert packing.pack(df, f"{TOKENIZERS}/word_bpe_49k.json").filter("length > 4096").count() == 0


def test_empty_tables(spark):
    df = spark.createDataFrame([], DOCS + ", i long, t long")
    assert language_id.language_id(df).count() == 0
    assert pii.find_pii(df).count() == 0
    assert token_counts.count_tokens(df, f"{TOKENIZERS}/byte_bpe_50k.tiktoken", BYTE_PATTERN).count() == 0
    assert decontaminate.find_items(df, spark.createDataFrame([(1, "a b c d e f")], "item_id long, text string")).count() == 0
    talk = spark.createDataFrame([], "conv_id long, turn long, role string, text string, seq long, kind string")
    assert chat_format.digest(chat_format.read_back(chat_format.render(chat_format.fold(chat_format.as_events(talk))))).count() == 0


def test_event_log_folds_back(spark):
    rows = [(c, t, "user" if t % 2 else "assistant", x) for c in (1, None) for t, x in enumerate(["", "a", "né</s>", None, "same", "same", "long " * 40])] + [(1, 3, "assistant", "again")]
    df = spark.createDataFrame([(*r, 5, "delta") for r in rows], "conv_id long, turn long, role string, text string, seq long, kind string")
    log = chat_format.as_events(df)
    assert {r["kind"] for r in log.select("kind").distinct().collect()} == {"message", "delta", "edit", "regenerate"}
    got = Counter((r["conv_id"], r["role"], r["text"]) for r in chat_format.fold(log).collect())
    assert got == Counter((c, r, x or "") for c, _, r, x in rows)


def lines_kept(docs):
    seen, out = [], []
    for i, t in docs:
        kept = []
        for s in (t or "").split("\n"):
            x = frozenset(WORD.findall(s.translate(LOW)))
            if not (x and any(100 * len(x & y) >= 75 * len(x | y) for y in seen)):
                kept.append(s)
            if x:
                seen.append(x)
        out.append((i, "\n".join(kept), len(kept) < (t or "").count("\n") + 1))
    return out


def shingles(t):
    w = WORD.findall(t.translate(LOW))
    return frozenset(" ".join(w[k : k + 5]) for k in range(max(1, len(w) - 4))) if w else frozenset()


def test_pipeline_by_brute_force(spark, tmp_path):
    rng = random.Random(12)
    vocab = ["".join(rng.choice("abcdefgh") for _ in range(rng.randint(2, 6))) for _ in range(400)]
    line = lambda n: " ".join(rng.choice(vocab) for _ in range(n))
    shared, item = line(12), line(30)
    docs = []
    for k in range(40):
        docs.append((k, "\n".join([line(25), shared if k % 5 == 0 else line(9), line(20) + (f" {item} " if k in (4, 33) else "") + line(9)])))
    near = [w for w in docs[11][1].split(" ")]
    near[3] = "edited"
    docs += [(40, " ".join(near)), (41, docs[12][1]), (42, None), (43, "123 !!"), (44, ""), (45, shared)]
    df = spark.createDataFrame([(i, t, "xx", "s", len(t or "")) for i, t in docs], DOCS)
    df.repartition(3).write.parquet(f"{tmp_path}/documents.parquet")
    spark.createDataFrame([(1, item), (2, None)], "item_id long, text string").write.parquet(f"{tmp_path}/benchmark.parquet")
    got = corpus_pipeline.run(spark, str(tmp_path)).collect()
    left = lines_kept([(i, t) for i, t in docs if t and any(c.isalpha() for c in t)])
    left = [(i, t) for i, t, cut in left if not cut or WORD.search(t)]
    root = {i: i for i, _ in left}
    sets = {i: shingles(t) for i, t in left}
    for i, _ in left:
        for j, _ in left:
            if j < i and sets[i] and 100 * len(sets[i] & sets[j]) >= 75 * len(sets[i] | sets[j]):
                root = {k: min(root[i], root[j]) if v in (root[i], root[j]) else v for k, v in root.items()}
    bench = shingles(item)
    clean = [(i, t) for i, t in left if root[i] == i and 100 * len(bench & sets[i]) < 75 * len(bench)]
    tok = packing.ChunkTokenizer(f"{TOKENIZERS}/word_bpe_49k.json").tokenizer
    want = Counter((i, zlib.crc32(np.array(tok.encode(t, add_special_tokens=False).ids + [1], "<u4").tobytes())) for i, t in clean)
    assert Counter((r["doc_id"], r["ids_crc32"]) for r in got) == want
    assert {i for i, _ in clean} == set(range(40)) - {4, 33}


def test_chat_format_folds_events(spark, monkeypatch):
    """The query goes through the fold of events, which keeps repeated turns."""
    from provgraph.llm import queries as text

    rows = [(1, 0, "user", "a"), (1, 1, "assistant", "x"), (1, 1, "assistant", None), (1, 1, "assistant", "x"), (2, None, None, None), (None, 0, "assistant", "ok")]
    df = spark.createDataFrame(rows, "conv_id long, turn long, role string, text string")
    a, b = (chat_format.render(x) for x in (df, chat_format.fold(chat_format.as_events(df))))
    assert sorted(map(str, a.collect())) == sorted(map(str, b.collect()))
    fold, seen = chat_format.fold, []
    monkeypatch.setattr(chat_format, "fold", lambda e: seen.append(e.columns) or fold(e))
    text.op10_chat_format(spark, "/root/testdata/sf0.001")
    assert seen == [["conv_id", "turn", "seq", "kind", "role", "text"]]


def test_limit_of_spoken_addresses():
    """The stated limit of op5: a spoken "at" needs a spoken dot and a known last part."""
    found = [pii.added(t, pii.detect(t))["email"] for t in ("jane at example dot com", "jane at example dot gr", "jane at example.com")]
    assert found == [[(0, 23)], [], []]
    assert "not found" in pii.find_pii.__doc__
