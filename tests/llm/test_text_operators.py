"""The text operators against brute force on small fixtures: nulls, empty and repeated rows, ties, clashing columns."""

import hashlib
import random
import re
import zlib
from collections import Counter

import numpy as np
import pytest

from provgraph.llm import chat_format, decontaminate, exact_dedup, language_id, line_dedup, ngram_join, packing, pii, substring_dedup, token_counts
from provgraph.llm.queries import BYTE_PATTERN, TOKENIZERS
from provgraph.llm.wordkernel import windows, words

LOW = str.maketrans("ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")
WORD = re.compile("[^\x20\x09-\x0d]+")
SCHEMA = "doc_id long, text string, lang string, source string, n_chars long, n long, node long"  # some names clash with the operators' own


@pytest.fixture(scope="module")
def corpus(spark):
    rng = random.Random(4)
    vocab = ["".join(rng.choice("abcdeéß") for _ in range(rng.randint(1, 6))) for _ in range(300)]
    passage = " ".join(rng.choice(vocab) for _ in range(30))
    texts = []
    for k in range(90):
        w = [rng.choice(vocab) for _ in range(rng.choice([0, 1, 3, 5, 13, 40, 90]))]
        t = " ".join(w)
        if k % 4 == 0:
            t += "\n" + passage
        texts.append(t)
    for k in range(30):  # near and exact copies of a few
        w = texts[20 + k % 5].split(" ")
        if w and k % 3:
            w[rng.randrange(len(w))] = "edited"
        texts.append(" ".join(w))
    texts += [None, "", "   \n\t", "A a\x0bB", "x" * 5000, "same line\nsame line\nSame LINE\n\nother"]
    rows = [(3 * i % 137, t, "xx", "s", 0, 7, 8) for i, t in enumerate(texts)]
    rows += [(None, texts[25], None, None, None, None, None), (None, None, None, None, None, None, None), rows[25], rows[25]]
    return rows, spark.createDataFrame(rows, SCHEMA).repartition(3)


def empty(spark):
    return spark.createDataFrame([], SCHEMA)


def test_word_kernel():
    data = "one  two\tthree\nONE".encode()
    h, s, e = words(data, True)
    assert [data[a:b] for a, b in zip(s, e, strict=True)] == [b"one", b"two", b"three", b"ONE"]
    assert h[0] == h[3] and len(set(h.tolist())) == 3
    big = (b"ab " * 400_000) + b"z" * 3_000_000 + b" end"
    assert len(words(big)[0]) == 400_002
    got = list(windows([b"a b c", b"", b"a b c d"], 3, whole_if_short=True))
    assert [len(x) for x, _ in got] == [1, 0, 2] and got[0][0][0] == got[2][0][0]


@pytest.mark.parametrize("keep", ["largest", "smallest"])
def test_exact_dedup(spark, corpus, keep):
    rows, df = corpus
    by = {}
    for i, t, *_ in rows:
        by.setdefault(t or "", []).append(i)
    got = exact_dedup.exact_dedup(df, keep=keep, rows_per_range=20).collect()
    assert len(got) == len(rows)
    digest = {hashlib.sha256(t.encode()).hexdigest(): t for t in by}
    kept = Counter()
    for r in got:
        ids = [x for x in by[digest[r["text_sha256"]]] if x is not None]
        want = (max if keep == "largest" else min)(ids) if ids else None
        assert r["keep_id"] == want and r["group_size"] == len(by[digest[r["text_sha256"]]])
        kept[r["text_sha256"]] += r["kept"]
    assert set(kept.values()) == {1}
    assert exact_dedup.exact_dedup(empty(spark)).count() == 0


def test_language_id(spark):
    rng = random.Random(1)
    syll = {"aa": ["ka", "lo", "mi"], "bb": ["ß", "ün", "ter"], "cc": ["ción", "el", "que"]}
    rows = []
    for i in range(240):
        y = "abc"[i % 3] * 2
        rows.append((i, " ".join("".join(rng.choice(syll[y]) for _ in range(3)) for _ in range(12)), y))
    rows += [(900, None, "aa"), (901, "123 ... !", "bb"), (902, "", None), (None, "kalomi kalo", None), (1, rows[1][1], "bb")]
    df = spark.createDataFrame(rows, "doc_id long, text string, lang string")
    got = language_id.language_id(df, landmarks=60).collect()
    assert len(got) == len(rows)
    truth = {i: y for i, _, y in rows[:240]}
    held = [r for r in got if r["held_out"] and r["doc_id"] in truth]
    assert len(held) > 40 and all(r["lang_pred"] == truth[r["doc_id"]] for r in held) and all(0 <= r["score"] <= 1 for r in got)
    assert {r["lang_pred"] for r in got if r["doc_id"] in (900, 901, 902)} == {"und"}
    assert all(r["held_out"] == (zlib.crc32(str(r["doc_id"]).encode()) % 3 == 1) for r in got if r["doc_id"] is not None)
    none = language_id.language_id(df.selectExpr("doc_id", "text", "cast(null as string) as lang")).collect()
    assert {r["lang_pred"] for r in none} == {"und"}
    kept = language_id.keep_identified(df, language_id.fitted(df, landmarks=60))
    assert kept.columns == df.columns and {r["doc_id"] for r in kept.collect()} >= set(truth) and not kept.filter("doc_id in (900, 901, 902)").collect()


def line_sets(text):
    return [(s, frozenset(WORD.findall(s.translate(LOW)))) for s in text.split("\n")]


def test_line_dedup(spark, corpus):
    rows, df = corpus
    out = [r.asDict() for r in line_dedup.remove_lines(df).collect()]
    assert len(out) == len(rows) and {"doc_id", "text", "n", "node", "n_lines", "n_removed"} <= set(out[0])
    places = [((i is not None, i or 0), k, x) for i, t, *_ in rows for k, (_, x) in enumerate(line_sets(t or "")) if x]

    def gone(i, k, x):
        return any(((j, m) < ((i is not None, i or 0), k)) and 100 * len(x & y) >= 75 * len(x | y) for j, m, y in places)

    want = Counter((i, None if t is None else "\n".join(s for k, (s, x) in enumerate(line_sets(t)) if not (x and gone(i, k, x)))) for i, t, *_ in rows)
    assert Counter((r["doc_id"], r["text"]) for r in out) == want
    assert line_dedup.remove_lines(empty(spark)).count() == 0


def shingles(t):
    w = WORD.findall((t or "").translate(LOW))
    return frozenset(" ".join(w[k : k + 5]) for k in range(max(1, len(w) - 4))) if w else frozenset()


def test_ngram_join(spark, corpus):
    rows, df = corpus
    sets = [shingles(t) for _, t, *_ in rows]
    root = list(range(len(rows)))

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    for a in range(len(rows)):
        for b in range(a):
            if sets[a] and sets[b] and 100 * len(sets[a] & sets[b]) >= 75 * len(sets[a] | sets[b]):
                root[find(a)] = find(b)
    least = {}
    for k, (i, *_) in enumerate(rows):
        if i is not None:
            least[find(k)] = min(i, least.get(find(k), i))
    want = Counter((i, len(sets[k]), least.get(find(k), i) if sets[k] else i) for k, (i, *_) in enumerate(rows))
    got = ngram_join.ngram_components(df).collect()
    assert Counter((r["doc_id"], r["n_shingles"], r["component_id"]) for r in got) == want
    one = ngram_join.one_of_each(df)
    assert one.columns == df.columns
    kept = one.collect()
    ids = Counter(r["doc_id"] for r in kept if r["doc_id"] is not None and shingles(r["text"]))
    assert set(ids) == {c for _, n, c in want if n and c is not None} and set(ids.values()) == {1}
    assert ngram_join.ngram_components(empty(spark)).count() == 0
    split = ngram_join.ngram_components(df, per_block=4, thin_rounds=0).collect()  # blocks of over four nodes go to several tasks
    assert Counter((r["doc_id"], r["n_shingles"], r["component_id"]) for r in split) == want


@pytest.mark.parametrize("leaf", [8, 24])
def test_tree_join_loses_nothing(leaf):
    rng = np.random.Generator(np.random.PCG64(3))
    vec = rng.integers(0, 4, (900, ngram_join.GROUPS)).astype(np.uint8)
    vec[600:] = vec[:300] + (rng.random((300, ngram_join.GROUPS)) < 0.05)
    n, root = vec.astype(int).sum(1), np.arange(900)
    root[:40] = 7  # a component that fills leaves
    p = ngram_join.Postings(n, np.zeros(900, int), vec, root, np.full((900, ngram_join.HEAD), -1), np.zeros(900, int), np.full(900, -1))
    x, y = ngram_join.tree_join(p, 75, leaf, 3)
    want = {(a, b) for a in range(900) for b in range(a) if root[a] != root[b] and np.minimum(vec[a], vec[b]).astype(int).sum() >= ngram_join.need(n[a], n[b], 75)}
    got = [(max(p, q), min(p, q)) for p, q in zip(x.tolist(), y.tolist(), strict=True)]
    assert set(got) == want and len(got) == len(want) and len(want) >= 300


def test_pairs_are_left_to_their_first_common_block():
    rng = np.random.Generator(np.random.PCG64(5))
    prefixes = [np.sort(rng.choice(40, 12, replace=False)) for _ in range(60)]
    rows = [(k, t, i) for k, p in enumerate(prefixes) for i, t in enumerate(p.tolist())]
    node, token, at = (np.array(c) for c in zip(*rows, strict=True))
    head = np.array([prefixes[k][: ngram_join.HEAD] for k in node])
    same = np.ones((len(node), ngram_join.GROUPS), np.uint8)
    p = ngram_join.Postings(np.full(len(node), 50), at, same, node, head, token, np.full(len(node), -1))
    x, y = ngram_join.block_pairs(token, p, 0, 8)
    want = {(a, b) for a in range(60) for b in range(a) if set(prefixes[a]) & set(prefixes[b])}
    got = [(max(node[i], node[j]), min(node[i], node[j])) for i, j in zip(x, y, strict=True)]
    assert set(got) == want
    early = [q for q in got if set(prefixes[q[0]][: ngram_join.HEAD]) & set(prefixes[q[1]][: ngram_join.HEAD])]
    assert len(early) == len(set(early)) > 500


def test_packing(spark, corpus):
    rows, df = corpus
    tok = packing.ChunkTokenizer(f"{TOKENIZERS}/word_bpe_49k.json").tokenizer
    placed = packing.pack(df, f"{TOKENIZERS}/word_bpe_49k.json", 64, with_ids=True)
    got = placed.collect()
    want = Counter()
    for i, t, *_ in rows:
        ids = tok.encode(t or "", add_special_tokens=False).ids + [1]
        for k, s in enumerate(range(0, len(ids), 64)):
            part = np.array(ids[s : s + 64], "<u4")
            want[i, k, s, len(part), zlib.crc32(part.tobytes())] += 1
    assert Counter((r["doc_id"], r["piece"], r["start"], r["length"], r["ids_crc32"]) for r in got) == want
    by = {}
    for r in got:
        by.setdefault(r["sequence_id"], []).append((r["offset"], r["length"]))
    for parts in by.values():
        at = 0
        for o, n in sorted(parts):
            assert o == at
            at += n
        assert at <= 64
    assert len(by) <= -(-sum(r["length"] for r in got) // 64) * 1.2 + 1
    seqs = {r["sequence_id"]: r["ids"] for r in packing.sequences(placed).collect()}
    assert all(seqs[r["sequence_id"]][r["offset"] : r["offset"] + r["length"]] == r["ids"] for r in got)
    assert packing.pack(empty(spark), f"{TOKENIZERS}/word_bpe_49k.json").count() == 0


def test_packing_plan_is_tight():
    rng = random.Random(2)
    for _ in range(5):
        counts = Counter(rng.choice([rng.randint(1, 100), rng.randint(1, 1000)]) for _ in range(3000))
        best = min((packing.plan_packing(counts, 1000, g, s, 8).sequences for s, g in packing.SCHEMES))
        assert best <= -(-sum(n * c for n, c in counts.items()) // 1000) * 1.03 + 2


def test_chunk_tokenizer_agrees():
    tok = packing.ChunkTokenizer(f"{TOKENIZERS}/word_bpe_49k.json", most=50)
    texts = ["It's a Test. The U.S.A., e.g. 3.14,15... DON'T", "ÉCOLE école Straße ΟΔΟΣ.", "a b c\x1cd", "", "<|endoftext|> end.", "İstanbul İ. ﬁ"]
    for _ in range(2):
        ids, cut = tok.encode([t.encode() for t in texts])
        for k, t in enumerate(texts):
            assert ids[cut[k] : cut[k + 1]].tolist() == tok.tokenizer.encode(t, add_special_tokens=False).ids


BASE = {
    "email": re.compile(r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+"),
    "ip": re.compile(r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)"),
    "card": re.compile(r"[0-9]([\x20-]?[0-9])+"),
    "phone": re.compile(r"\+[0-9][\x20().0-9-]+[0-9]"),
}


def plain_spans(t):
    def ok(kind, m):
        d = re.sub("[^0-9]", "", m)
        return {"email": True, "ip": all(int(x) <= 255 for x in m.split(".")) if kind == "ip" else 0, "card": 12 <= len(d) <= 19 and pii.luhn(d), "phone": 9 <= len(d) <= 15}[kind]

    return {k: [m.span() for m in p.finditer(t) if ok(k, m.group())] for k, p in BASE.items()}


def test_pii_base_spans():
    rng = random.Random(8)
    for _ in range(4000):
        t = "".join(rng.choice(["a", "1", "4", "@", ".", "+", " ", "-", "(", "é", "255", "4111 1111 1111 1111"]) for _ in range(rng.randint(0, 25)))
        assert pii.detect(t) == plain_spans(t), t


@pytest.mark.parametrize(
    ("text", "kind", "part"),
    [
        ("mail john [at] example (dot) com now", "email", "john [at] example (dot) com"),
        ("write to john dot smith at example dot com please", "email", "john dot smith at example dot com"),
        ("call plus one five five five zero one nine nine two three", "phone", "plus one five five five zero one nine nine two three"),
        ("from １９２.168.1.1 on", "ip", "１９２.168.1.1"),
        ("with jоhn@ехаmple.com on", "email", "jоhn@ехаmple.com"),
        ("ip one nine two dot one six eight dot one dot one", "ip", "one nine two dot one six eight dot one dot one"),
        ("user&#64;host&#46;org", "email", "user&#64;host&#46;org"),
    ],
)
def test_pii_disguises(text, kind, part):
    more = pii.added(text, pii.detect(text))
    assert [text[a:b] for a, b in more[kind]] == [part]


def test_pii_leaves_clean_text(spark):
    for t in ("we met at the dot of noon", "one two or three", "Étre de la même", "at home (at last) . com"):
        assert not any(pii.added(t, pii.detect(t)).values())
    rows = [(1, None), (2, "a@b.co, +44 20 7946 0958"), (None, "10.0.0.1")]
    got = {r["doc_id"]: r for r in pii.find_pii(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    assert got[2]["spans"] == "email:0:6,phone:8:24" and got[None]["n_ip"] == 1 and got[1]["spans"] == ""


def test_token_counts():
    counter = token_counts.SegmentCounter(f"{TOKENIZERS}/byte_bpe_50k.tiktoken", BYTE_PATTERN)
    rng = random.Random(5)
    for _ in range(600):
        t = "".join(rng.choice("ab c\n  d'.1é\t") for _ in range(rng.randint(0, 60)))
        tree = token_counts.CountTree(t, counter, leaf=rng.choice([1, 2, 5]))
        for _ in range(4):
            a = rng.randint(0, len(t))
            b = rng.randint(a, len(t))
            new = "".join(rng.choice("ab c\n  d'.1é\t") for _ in range(rng.randint(0, 8)))
            t = t[:a] + new + t[b:]
            tree.edit(a, b, new)
            assert tree.text == t and tree.tokens == len(counter.encoding.encode_ordinary(t))
    long = token_counts.CountTree("word " * 50_000, counter)
    assert long.edit(100_000, 100_005, "other ") < 300


def test_token_counts_query(spark, corpus):
    rows, df = corpus
    enc = token_counts.SegmentCounter(f"{TOKENIZERS}/byte_bpe_50k.tiktoken", BYTE_PATTERN).encoding
    got = token_counts.count_tokens(df.withColumn("e", token_counts.stated_edits()), f"{TOKENIZERS}/byte_bpe_50k.tiktoken", BYTE_PATTERN, "e").collect()

    def edited(t):
        n, cut = len(t), len(t) // 10
        return (t[: n // 2] + "edited " + t[n // 2 :])[cut:] + "\nThe end."

    want = Counter((i, len(enc.encode_ordinary(t or "")), len(enc.encode_ordinary(edited(t or "")))) for i, t, *_ in rows)
    assert Counter((r["doc_id"], r["n_tokens"], r["n_tokens_edited"]) for r in got) == want


def test_decontamination(spark, corpus):
    rows, df = corpus
    rng = random.Random(6)
    pool = [t for _, t, *_ in rows if t and len(t.split()) >= 40]
    items = [(k, " ".join(pool[k % len(pool)].split()[k % 9 : k % 9 + rng.randint(4, 30)])) for k in range(25)] + [(25, None), (26, ""), (27, "no such words at all here"), (None, pool[0])]
    bench = spark.createDataFrame(items, "item_id long, text string")
    sets = [(k, shingles(t)) for k, t in items]
    want = Counter()
    for i, t, *_ in rows:
        own = shingles(t)
        hit = [(k, len(s & own)) for k, s in sets if s and 100 * len(s & own) >= 75 * len(s)]
        want[i, len(hit), ",".join(str(k) for k in sorted(k for k, _ in hit if k is not None))] += 1
    for block in (7, 20_000):
        got = decontaminate.find_items(df, bench, block=block).collect()
        assert Counter((r["doc_id"], r["n_items"], r["item_ids"]) for r in got) == want
    clean = decontaminate.drop_contaminated(df, bench, block=7)
    assert clean.count() == sum(c for (_, n, _), c in want.items() if not n) and clean.columns == df.columns
    assert decontaminate.drop_contaminated(df, bench.limit(0)).count() == len(rows)


def test_substring_dedup(spark, corpus):
    rows, df = corpus
    texts = [(i, WORD.findall(t or "")) for i, t, *_ in rows]
    first = {}
    for i, w in texts:
        for k in range(len(w) - 12):
            key = tuple(w[k : k + 13])
            if i is not None:
                first[key] = min(i, first.get(key, i))
    want = Counter()
    for i, w in texts:
        gone = [False] * len(w)
        for k in range(len(w) - 12):
            if i is not None and first[tuple(w[k : k + 13])] < i:
                gone[k : k + 13] = [True] * 13
        kept = " ".join(x for x, g in zip(w, gone, strict=True) if not g)
        want[i, len(w), sum(gone), hashlib.sha256(kept.encode()).hexdigest()] += 1
    got = substring_dedup.remove_repeats(df).collect()
    assert Counter(tuple(r) for r in got) == want and sum(n * c for (_, _, n, _), c in want.items()) > 0
    assert substring_dedup.remove_repeats(empty(spark)).count() == 0


def test_chat_format(spark):
    rows = [(1, 0, "user", "a</s>b\\"), (1, 1, "assistant", "[INST]\\s>x</s>[/INST]"), (1, 1, "assistant", None), (2, None, None, None), (None, 0, "assistant", "ok"), (3, 0, "sys<s>", "<\\s>\\b[/INST"), (3, 1, "assistant", "")]
    df = spark.createDataFrame(rows, "conv_id long, turn long, role string, text string")
    back = {r["conv_id"]: r for r in chat_format.read_back(chat_format.render(df)).collect()}
    for cid in (1, 2, 3, None):
        own = sorted(((r[1] is not None, r[1] or 0, r[2] or "", r[3] or "") for r in rows if r[0] == cid))
        assert [(t["role"], t["text"]) for t in back[cid]["turns"]] == [(r, t) for *_, r, t in own]
        assert back[cid]["loss_text"] == "".join(t for *_, r, t in own if r == "assistant")
    log = [(1, 0, 0, "delta", "user", "hel"), (1, 0, 1, "delta", "user", "lo"), (1, 1, 0, None, "assistant", "old"), (1, 1, 1, "edit", "assistant", "new"), (1, 2, 0, "delta", "assistant", "x"), (1, 2, 1, "regenerate", "assistant", None), (1, 2, 2, "delta", "assistant", "y")]
    f = chat_format.fold(spark.createDataFrame(log, "conv_id long, turn long, seq long, kind string, role string, text string"))
    assert [(r["role"], r["text"]) for r in f.orderBy("turn").collect()] == [("user", "hello"), ("assistant", "new"), ("assistant", "y")]
    plan = chat_format.digest(chat_format.read_back(chat_format.render(df)))._jdf.queryExecution().toString()
    assert not re.search("Python|Arrow|Pandas", plan)


def test_pipeline_small(spark, corpus, tmp_path):
    import corpus_pipeline

    rows, df = corpus
    sf = f"file://{tmp_path}"
    df.write.parquet(f"{sf}/documents.parquet")
    spark.createDataFrame([(0, rows[30][1])], "item_id long, text string").write.parquet(f"{sf}/benchmark.parquet")
    docs, kept = spark.read.parquet(f"{sf}/documents.parquet"), []
    for name, stage in corpus_pipeline.STAGES:
        docs = stage(spark, docs, sf)
        docs.write.parquet(f"{sf}/{name}")
        docs = spark.read.parquet(f"{sf}/{name}")
        kept.append(docs.count())
        if name != corpus_pipeline.STAGES[-1][0]:
            assert set(docs.columns) == set(df.columns)
    assert kept[0] >= kept[1] >= kept[2] >= kept[3] > 0
