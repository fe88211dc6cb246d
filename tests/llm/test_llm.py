"""Operators on training data against brute force, on small tables with every odd case."""

import collections
import hashlib
import random
import zlib

import numpy as np
import pytest

import corpus_pipeline
from semigrid.llm import exact_dedup, language_id, lm_scoring, packing, piece_codec, quality_rules, simhash_dedup, suffix_dedup, token_counts, url_filter
from semigrid.llm.bwt import window_classes
from semigrid.llm.golay import Golay
from semigrid.llm.queries import vocabulary

SCHEMA = "doc_id long, text string, lang string, source string, n_chars long"
PASSAGE = " ".join(f"passage{k}" for k in range(60))


def _words(n, seed):
    r = random.Random(seed)
    return " ".join("".join(r.choice("abcdefghiklmnoprstu") for _ in range(r.randint(2, 9))) for _ in range(n))


def _rows():
    long = _words(30_000, 5)
    near = _words(300, 6).split(" ")
    texts = [
        None, "", " ", "\n\t ", "A", "a  b", " a\tb ", "a b", "Été à la plage, où l'été", "日本語 テキスト 😀 x", "nul\0byte", "▁marks ▁▁y", "<|endoftext|> <s> </s>", "123 456",
        _words(200, 1), _words(200, 1), _words(200, 2) + "\n" + PASSAGE + "\n" + _words(100, 3), PASSAGE + " " + _words(80, 4), long, long + " tail", "x" * 5000, "ab" * 400,
        " ".join(near), " ".join([*near[:150], "changed", *near[151:]]), "be " * 300, "### $$$ " * 60, "line one\nline one\n" * 40,
    ]
    rows = [(k, t, "en" if t and k % 2 else None, "s", 0) for k, t in enumerate(texts)]
    return rows + [(len(rows), _words(200, 1), None, None, None)]


@pytest.fixture(scope="module")
def docs(spark):
    return spark.createDataFrame(_rows(), SCHEMA).repartition(3).cache()


@pytest.fixture(scope="module")
def empty(spark):
    return spark.createDataFrame([], SCHEMA)


@pytest.fixture(scope="module")
def clashing(docs):
    """Other columns that bear names the operators use themselves."""
    out = docs
    for c in ("h", "body", "w", "fp", "node", "key", "spans", "kept", "n_tokens", "fingerprint", "count", "first", "score", "ids", "part", "_spans"):
        out = out.withColumn(c, out["doc_id"])
    return out


OPERATORS = {
    "exact": exact_dedup.exact_dedup,
    "rules": quality_rules.quality_rules,
    "codec": lambda d: piece_codec.piece_encode(d, vocabulary("piece_bpe_32k.model")),
    "simhash": simhash_dedup.simhash_components,
    "groups": simhash_dedup.similar_groups,
    "suffix": suffix_dedup.suffix_dedup,
    "cut": suffix_dedup.without_repeats,
    "language": language_id.query,
    "counts": lambda d: token_counts.token_counts(d, vocabulary("piece_bpe_32k.model")),
    "packing": lambda d: packing.pack(d, vocabulary("word_bpe_49k.json")),
    "lm": lm_scoring.query,
}


def _sorted(df, columns):
    return sorted(map(repr, df.select(*columns).collect()))


@pytest.mark.parametrize("name", OPERATORS)
def test_empty_and_clashing(name, docs, empty, clashing):
    plain = OPERATORS[name](docs)
    assert OPERATORS[name](empty).count() == 0
    if name != "packing":  # its order is that of partitions
        assert _sorted(OPERATORS[name](clashing), plain.columns) == _sorted(plain, plain.columns)


@pytest.mark.parametrize("name", OPERATORS)
def test_null_ids_and_repeated_rows(name, spark):
    rows = [(None, "some text here", "en", None, None), (None, None, None, None, None), (3, "same row again", "en", "a", 1), (3, "same row again", "en", "a", 1), (4, PASSAGE, "en", "a", 1), (4, PASSAGE, "en", "a", 1)]
    out = OPERATORS[name](spark.createDataFrame(rows, SCHEMA)).collect()
    if name not in ("groups", "packing"):
        assert len(out) == len(rows)
    if name == "suffix":
        assert all(r.n_removed == 0 for r in out)


def test_exact_dedup(docs):
    norm = {r[0]: exact_dedup.BLANKS and __import__("re").sub(r"[\x20\x09-\x0D]+", " ", r[1] or "") for r in _rows()}
    groups = collections.defaultdict(list)
    for k, t in norm.items():
        groups[t].append(k)
    for r in exact_dedup.exact_dedup(docs).collect():
        g = groups[norm[r.doc_id]]
        assert (r.keep_id, r.group_size, r.kept) == (min(g), len(g), r.doc_id == min(g))
        assert r.text_sha256 == hashlib.sha256(norm[r.doc_id].encode()).hexdigest()


def test_exact_dedup_with_colliding_hashes(docs):
    from pyspark.sql import functions as F

    weak = exact_dedup.exact_dedup(docs, hash_of=lambda t: F.unhex(F.substring(F.md5(t), 1, 1)))
    full = exact_dedup.exact_dedup(docs)
    assert _sorted(weak, full.columns) == _sorted(full, full.columns)


def test_exact_dedup_with_many_hashes(docs, monkeypatch):
    full = exact_dedup.exact_dedup(docs)
    want = _sorted(full, full.columns)
    monkeypatch.setattr(exact_dedup, "BROADCAST_BYTES", 0)
    assert _sorted(exact_dedup.exact_dedup(docs), full.columns) == want


def test_quality_rules(docs):
    import re

    for r in quality_rules.quality_rules(docs).collect():
        text = dict((x[0], x[1]) for x in _rows())[r.doc_id] or ""
        w = [x for x in re.split(r"[\x20\x09-\x0D]+", text) if x]
        tri = collections.Counter(zip(w, w[1:], w[2:]))
        hit = {i + k for i in range(len(w) - 2) if tri[tuple(w[i : i + 3])] > 1 for k in range(3)}
        lines = [x for x in text.split("\n") if re.search(r"[^\x20\x09-\x0D]", x)]
        assert (r.n_words, r.word_chars, r.n_repeat_words, r.n_dup_lines) == (len(w), sum(map(len, w)), len(hit), len(lines) - len(set(lines)))
        assert r.n_symbols == len(re.findall(r"[#*$%&|<>]", text))
        assert r.base_failed == (len(w) < 50 or 100 * len(hit) > 50 * len(w))
        assert not (r.base_failed and r.kept)


def test_url_filter(spark):
    urls = [None, "", "no scheme", "http://Example.ORG/es/1?x", "http://a.b.org/en/1", "ftp://x.com/fr/", "http://x.com/de/1#y", "http://notorg/", "http://org", "a://b://c/d", "http://x.example.org/en/12", "https://cheap-pills.test/en/9", "http://é.net?q=/fr/"]
    df = spark.createDataFrame(list(enumerate(urls)), "page_id long, url string")
    rows = {r.page_id: r for r in url_filter.url_filter(df).collect()}
    for k, u in enumerate(urls):
        assert (rows[k].host, rows[k].path) == url_filter._split(u or "")
    assert [rows[k].rule for k in (3, 4, 5, 6, 7, 8, 10)] == ["example.org/es/", "org/", "com/fr/", "com/de/", None, None, "example.org/en/1"]
    assert [rows[k].verdict for k in (3, 4, 5, 6, 10, 11)] == ["block", "allow", "allow", "block", "block", "block"]
    w, b = url_filter.train()
    for k, u in enumerate(urls):
        host, path = url_filter._split(u or "")
        found = url_filter._buckets(f"^{host}|{path}$")
        assert rows[k].score == sum(w[x] for x in found) + max(1, len(found)) * b
    assert url_filter.url_filter(df.limit(0)).count() == 0
    assert url_filter.held_out_accuracy(parts=2) >= 0.9
    table = url_filter.labelled_urls()
    paths = [{url_filter._split(u)[1] for u, label in table if label == k} for k in (0, 1)]
    assert sum(label for _, label in table) == len(table) // 2 and len(paths[0] & paths[1]) < len(paths[0]) // 4


def test_piece_codec_and_counts(docs):
    import sentencepiece

    path = vocabulary("piece_bpe_32k.model")
    sp = sentencepiece.SentencePieceProcessor(model_file=path)
    texts = {r[0]: r[1] or "" for r in _rows()}
    for r in piece_codec.piece_encode(docs, path).collect():
        ids = sp.encode(texts[r.doc_id], add_eos=True)
        assert list(r.ids) == ids and r.decoded == sp.decode(ids)
    for r in token_counts.token_counts(docs, path, limit=100).collect():
        n = len(sp.encode(texts[r.doc_id]))
        assert (r.n_tokens, r.n_bytes, r.over_limit) == (n, len(texts[r.doc_id].encode()), n > 100)


def test_piece_table_and_decoding(docs, empty):
    """The corpus-wide table gives what the library gives, each distinct word is segmented once, and ids turn into text."""
    import sentencepiece

    path = vocabulary("piece_bpe_32k.model")
    sp = sentencepiece.SentencePieceProcessor(model_file=path)
    texts = {r[0]: r[1] or "" for r in _rows()}
    coded = piece_codec.encode_by_table(docs, path).cache()
    for r in coded.collect():
        ids = sp.encode(texts[r.doc_id], add_eos=True)
        assert (list(r.ids), r.n_tokens, r.decoded) == (ids, len(ids), sp.decode(ids))
    assert {r.doc_id: r.decoded for r in piece_codec.piece_decode(coded, path).collect()} == {k: sp.decode(sp.encode(t)) for k, t in texts.items()}
    assert piece_codec.encode_by_table(empty, path).count() == piece_codec.piece_decode(coded.limit(0), path).count() == 0
    chunks = docs.sparkSession.createDataFrame([("word",), ("word",), (None,), ("",)], "chunk string")
    assert sorted(r.chunk for r in piece_codec.chunk_table(chunks, path).collect()) == ["", "word"]


def test_golay_keys_never_miss():
    golay, r = Golay(), np.random.default_rng(1)
    n = 4000
    x = r.integers(-(2**63), 2**63, n, dtype=np.int64)
    y = x.copy()
    for _ in range(3):
        y ^= np.where(r.random(n) < 0.9, np.int64(1) << r.integers(0, 64, n), np.int64(0))

    def keys(v):
        out = collections.defaultdict(set)
        for rows, k in simhash_dedup.golay_keys(golay, v):
            for a, b in zip(rows.tolist(), k.tolist()):
                out[a].add(b)
        return out

    a, b = keys(x), keys(y)
    assert not any(a[i].isdisjoint(b[i]) for i in range(n))


def test_simhash_components(spark):
    import xxhash

    r = random.Random(3)
    base = [_words(120, s).split(" ") for s in range(40)]
    texts = [" ".join(w) for w in base]
    for w in base[:20]:
        for _ in range(6):
            v = list(w)
            v[r.randrange(len(v))] = "new"
            texts.append(" ".join(v))
    texts += ["", None, "one", "Two words"]

    def fp(t):
        w = (t or "").lower().split()
        s = [" ".join(w[i : i + 3]) for i in range(max(1, len(w) - 2))] if w else []
        h = [xxhash.xxh64_intdigest(x.encode(), 42) for x in s]
        return sum(1 << k for k in range(64) if 2 * sum(v >> k & 1 for v in h) > len(h))

    prints = [fp(t) for t in texts]
    root = list(range(len(texts)))

    def find(i):
        while root[i] != i:
            i = root[i]
        return i

    for i in range(len(texts)):
        for j in range(i):
            if (prints[i] ^ prints[j]).bit_count() <= 3:
                a, b = sorted((find(i), find(j)))
                root[b] = a
    df = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    for limit in (50_000, 2):
        for x in simhash_dedup.simhash_components(df, run_limit=limit).collect():
            assert (x.fingerprint, x.component_id) == (f"{prints[x.doc_id]:016x}", find(x.doc_id))


def test_window_classes():
    r = np.random.default_rng(0)
    for _ in range(60):
        base = r.integers(97, 97 + r.integers(1, 5), 50).astype(np.uint8)
        strings = [base[slice(*sorted(r.integers(0, 51, 2)))].copy() for _ in range(5)]
        least = int(r.integers(1, 10))
        seen, back = {}, {}
        for s, labels in zip(strings, window_classes(strings, least)):
            assert len(labels) == max(0, len(s) - least + 1)
            for i, v in enumerate(labels):
                w = s[i : i + least].tobytes()
                assert seen.setdefault(w, v) == v and back.setdefault(v, w) == w


@pytest.mark.parametrize("limits", [{}, {"crowd": 1, "held": 500}, {"run_limit": 3}])
def test_suffix_dedup(docs, limits):
    seen, want = set(), {}
    for k, t, *_ in _rows():
        b = (t or "").encode()
        gone = np.zeros(len(b), bool)
        for p in range(len(b) - 99):
            w = b[p : p + 100]
            if w in seen:
                gone[p : p + 100] = True
            seen.add(w)
        kept = bytes(np.frombuffer(b, np.uint8)[~gone])
        want[k] = (len(b), int(gone.sum()), int((np.diff(np.r_[0, gone.astype(int)]) == 1).sum()), hashlib.sha256(kept).hexdigest())
    for r in suffix_dedup.suffix_dedup(docs, **limits).collect():
        assert (r.n_bytes, r.n_removed, r.n_spans, r.kept_sha256) == want[r.doc_id]


def test_suffix_dedup_of_one_text_many_times(spark, monkeypatch):
    """Copies and variants of one text: its strings are asked for in parts, and results are those of brute force."""
    monkeypatch.setattr(suffix_dedup, "_ASKED", 2)
    base = _words(60, 70)
    texts = [base] * 30 + [base[:k] + "#" + base[k:] for k in range(20, 300, 17)] + [base[100:], "ab" * 200]
    seen, want = set(), {}
    for k, t in enumerate(texts):
        b = t.encode()
        gone = np.zeros(len(b), bool)
        for p in range(len(b) - 99):
            if b[p : p + 100] in seen:
                gone[p : p + 100] = True
            seen.add(b[p : p + 100])
        want[k] = (int(gone.sum()), hashlib.sha256(bytes(np.frombuffer(b, np.uint8)[~gone])).hexdigest())
    df = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string").repartition(4)
    assert {r.doc_id: (r.n_removed, r.kept_sha256) for r in suffix_dedup.suffix_dedup(df, held=50).collect()} == want


def test_digests_that_collide_remove_nothing(spark, monkeypatch):
    """Strings with one digest and different bytes are told apart on the texts."""
    import semigrid.llm.suffix_dedup as sd

    df = spark.createDataFrame([(1, _words(40, 80)), (2, _words(40, 81)), (3, _words(40, 80))], "doc_id long, text string")
    plain = {r.doc_id: r.n_removed for r in sd.suffix_dedup(df).collect()}
    assert plain[2] == 0 and plain[3] > 100
    first = sd._first_of
    # a grouping that takes every context for equal to the first one
    monkeypatch.setattr(sd, "_first_of", lambda keys, doc, start: first([np.zeros(len(doc), np.int64)], doc, start) if len(keys) == 2 else first(keys, doc, start))
    got = {r.doc_id: r.n_removed for r in sd.suffix_dedup(df).collect()}
    assert got[1] == got[2] == 0 and got[3] < plain[3]


def test_letters():
    assert language_id.letter_words("Été ²½ Ⅷ x² a1b ① ª日本 ΑΒ") == ["été", "x", "a", "b", "ª日本", "αβ"]
    assert language_id.letter_words("²½ Ⅷ ① 12 _ !") == []


def _brute_language(model, text):
    """Word-first backoff written out: a known word's log frequency, else the mean of its longest known n-grams."""
    import regex

    words = regex.findall(r"\p{L}+", (text or "").lower())
    if not words:
        return "und"
    total = [0.0] * len(model.languages)
    for w in words:
        if w in model.words:
            part = model.table[model.words[w]]
        else:
            marked, part = f"<{w}>", model.floor
            for size in range(min(model.longest, len(marked)), 0, -1):
                known = [marked[i : i + size] for i in range(len(marked) - size + 1) if marked[i : i + size] in model.grams]
                if known:
                    part = sum(model.table[model.grams[g]].astype(float) for g in known) / len(known)
                    break
        total = [x + float(y) for x, y in zip(total, part)]
    return model.languages[total.index(max(total))]


def test_language_id_against_brute_force(spark):
    r = random.Random(4)
    own = {lang: [_words(1, 1000 * k + i) for i in range(300)] for k, lang in enumerate(("aa", "bb", "cc"))}
    rows = []
    for k in range(300):
        lang = r.choice(list(own))
        words = [r.choice(own[lang]) if r.random() < 0.7 else _words(1, r.randrange(10**6)) for _ in range(r.randint(1, 30))]
        rows.append((k, r.choice(["", "¹ "]) + " ".join(words) + r.choice(["", " x²", " 12", "!"]), lang, None, None))
    rows += [(900, "²½ Ⅷ", "aa", None, None), (901, "", "aa", None, None), (None, " ".join(own["bb"][:9]), "bb", None, None)]
    df = spark.createDataFrame(rows, SCHEMA)
    model = language_id.fit(df.filter(~language_id.held_out()))
    got = {x.doc_id: x for x in language_id.query(df).collect()}
    assert all(got[k].lang_pred == _brute_language(model, text) for k, text, *_ in rows)
    assert got[None].held_out is False and got[900].lang_pred == "und"
    right = [got[k].lang_pred == lang for k, text, lang, *_ in rows[:300] if got[k].held_out]
    assert sum(right) >= 0.9 * len(right)


def test_language_sample_is_bounded(spark):
    """One row repeated many times fills one place of the sample."""
    rows = [(1, "same words again", "aa", None, None)] * 500 + [(k, f"other words number {'x' * (k % 7 + 1)}", "bb", None, None) for k in range(2, 60)]
    model = language_id.fit(spark.createDataFrame(rows, SCHEMA), sample=20)
    counts = language_id.fit(spark.createDataFrame([rows[0], *rows[500:]], SCHEMA), sample=20)
    assert model.words == counts.words and np.allclose(model.table, counts.table)


def test_language_id(spark):
    common = {"en": "the of and to in", "fr": "le la de et que", "de": "der die und das ist"}
    r = random.Random(1)
    rows = [(k, " ".join(r.choice(common[lang].split()) + ("" if r.random() < 0.7 else lang) for _ in range(30)), lang, None, None) for k in range(240) for lang in [r.choice(list(common))]]
    rows += [(1000, None, "en", None, None), (1001, "12 34 !!", None, None, None), (1002, "the and of", None, None, None)]
    got = {x.doc_id: x for x in language_id.query(spark.createDataFrame(rows, SCHEMA)).collect()}
    assert all(got[k].lang_pred == lang for k, _, lang, _, _ in rows[:240])
    assert got[1000].lang_pred == got[1001].lang_pred == "und" and got[1002].lang_pred == "en"
    assert all(0 <= x.score <= 1 and x.held_out == (zlib.crc32(str(k).encode()) % 3 == 1) for k, x in got.items())


def test_lm_gradient_and_scores(spark):
    r = np.random.default_rng(0)
    counts = r.integers(0, 5, (25, 5)).astype(float)
    net = lm_scoring.WindowNetwork.fresh(5, 3, 1)
    _, slopes = net.gradient(counts)
    for value, slope in zip((net.left, net.out, net.bias), (slopes[0], slopes[3], slopes[2])):
        at = np.unravel_index(1, value.shape)
        value[at] += 1e-5
        up = net.gradient(counts)[0]
        value[at] -= 2e-5
        down = net.gradient(counts)[0]
        value[at] += 1e-5
        assert abs((up - down) / 2e-5 - slope[at]) < 1e-6
    losses = net.train(counts, 50)
    assert losses[-1] < losses[0]
    rows = [(k, "to be or not to be that is the question " * 5, None, None, None) for k in range(30)] + [(99, "be to or question not the is that to be " * 5, None, None, None), (100, None, None, None, None)]
    df = spark.createDataFrame(rows, SCHEMA)
    model = lm_scoring.fit(df)
    got = {x.doc_id: x for x in lm_scoring.score(df, model).collect()}
    assert got[0].mean_log_prob > got[99].mean_log_prob and got[100].pseudo_log_likelihood == 0


@pytest.mark.parametrize("carried", [200_000, 150])
def test_lm_scores_every_word_by_its_own_probability(spark, carried):
    """Scores against the counts of all words, whether they are carried or joined."""
    r = random.Random(2)
    vocabulary = _words(400, 9).split(" ")
    texts = [" ".join(r.choices(vocabulary, k=r.randint(0, 60))) for _ in range(80)] + [_words(40, 77)] + [_words(40, 78)] * 2 + [None]
    df = spark.createDataFrame([(k, t, None, None, None) for k, t in enumerate(texts)], SCHEMA).repartition(3)
    model = lm_scoring.fit(df, carried=carried)
    counts = collections.Counter(w for t in texts for w in (t or "").split())
    assert {x.word: x.n for x in model.counts.collect()} == dict(counts)
    assert (len(model.carried) < len(counts)) == (carried == 150)
    in_class = collections.Counter()
    for w, n in counts.items():
        in_class[model.classes[w]] += n
    table = model.network.log_probs()
    got = {x.doc_id: x for x in lm_scoring.score(df, model).collect()}
    for k, t in enumerate(texts):
        words = (t or "").split()
        ids = [0, *(model.classes[w] for w in words), 0]
        want = sum(table[ids[i] * lm_scoring.CLASSES + ids[i + 2], ids[i + 1]] + np.log(counts[w] / in_class[ids[i + 1]]) for i, w in enumerate(words))
        assert got[k].n_tokens == len(words) and abs(got[k].pseudo_log_likelihood - want) < 1e-3 * max(1, len(words))
    assert got[81].mean_log_prob > got[80].mean_log_prob, "the text that the corpus holds twice is likelier"


def test_lm_probabilities_sum_to_one(spark):
    df = spark.createDataFrame([(1, "a b a c dd ee dd f", None, None, None), (2, "ee a b", None, None, None)], SCHEMA)
    model = lm_scoring.fit(df)
    words = {x.word: x.n for x in model.counts.collect()}
    each = collections.Counter()
    for w, n in words.items():
        each[model.classes[w]] += n / model.totals[model.classes[w]]
    assert all(abs(v - 1) < 1e-9 for v in each.values())
    assert np.allclose(np.exp(model.network.log_probs()).sum(1), 1)


@pytest.mark.parametrize("options", [{}, {"size": 64, "windows": 2, "least_cut": 1}])
def test_packing(docs, options):
    from tokenizers import Tokenizer

    size = options.get("size", 2048)
    tokenizer = Tokenizer.from_file(vocabulary("word_bpe_49k.json"))
    ids = {r[0]: np.array([*tokenizer.encode(r[1] or "", add_special_tokens=False).ids, 1], "<u4") for r in _rows()}
    rows = packing.pack(docs, vocabulary("word_bpe_49k.json"), **options).collect()
    pieces, windows = collections.defaultdict(list), collections.defaultdict(list)
    for r in rows:
        pieces[r.doc_id].append(r)
        windows[r.sequence_id].append(r)
        assert r.ids_crc32 == zlib.crc32(ids[r.doc_id][r.start : r.start + r.length].tobytes()) and r.doc_tokens == len(ids[r.doc_id])
    for k, v in ids.items():
        at = 0
        for r in sorted(pieces[k], key=lambda r: r.start):
            assert r.start == at
            at += r.length
        assert at == len(v)
    padded = 0
    for w in windows.values():
        at = 0
        for r in sorted(w, key=lambda r: r.offset):
            assert r.offset == at
            at += r.length
        assert at <= size
        padded += 0 if at & (at - 1) == 0 else size - at
    assert padded <= 0.01 * sum(map(len, ids.values()))


def test_pipeline(spark, tmp_path):
    spark.createDataFrame(_rows(), SCHEMA).write.parquet(str(tmp_path / "documents.parquet"))
    docs = spark.read.parquet(str(tmp_path / "documents.parquet"))
    seen = []
    for name, stage in corpus_pipeline.STAGES[:-1]:
        before = docs
        docs = stage(spark, docs, str(tmp_path)).cache()
        assert docs.columns == before.columns
        seen.append({r.doc_id for r in docs.select("doc_id").collect()})
    letters = {k for k, t, *_ in _rows() if t and any(c.isalpha() for c in t)}
    assert seen[0] == letters
    assert 15 not in seen[1] and 14 in seen[1] and 7 not in seen[1]
    assert 22 in seen[2] and 23 not in seen[2] and 16 in seen[2]
    assert seen[3] == seen[2]
    assert PASSAGE not in {r.doc_id: r.text for r in docs.collect()}[17]
    assert corpus_pipeline.run(spark, str(tmp_path)).count() > 0


def test_pipeline_on_nothing(spark, empty, tmp_path):
    empty.write.parquet(str(tmp_path / "documents.parquet"))
    assert corpus_pipeline.run(spark, str(tmp_path)).count() == 0


def _brute_groups(texts, similarity=0.8):
    """doc_id to the least doc_id of its group, by comparing all pairs."""
    sets = [set(simhash_dedup.shingles(t or "", 5)) for t in texts]
    root = list(range(len(texts)))

    def find(i):
        while root[i] != i:
            i = root[i]
        return i

    for i in range(len(texts)):
        for j in range(i):
            both = len(sets[i] & sets[j])
            if both >= similarity * (len(sets[i]) + len(sets[j]) - both):
                a, b = sorted((find(i), find(j)))
                root[b] = a
    return {i: find(i) for i in range(len(texts)) if find(i) != i}


def _groups(spark, texts, **options):
    df = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    return {x.node: x.root for x in simhash_dedup.similar_groups(df, **options).collect()}


def _variants(n, seed):
    """Variants of one text, some near each other and not near the first; the first has the words in another order."""
    r = random.Random(seed)
    base = _words(120, seed).split(" ")
    out = [" ".join(r.sample(base, len(base))), " ".join(base)]
    for _ in range(n):
        w = list(base)
        for _ in range(r.randint(0, 4)):
            w[r.randrange(len(w))] = "new%d" % r.randrange(1000)
        out.append(" ".join(w))
    return out


def test_groups_of_one_word_set(spark):
    w = _words(80, 8).split(" ")
    texts = [" ".join(reversed(w)), " ".join(w), " ".join([*w[1:], w[0]])]
    assert _groups(spark, texts) == _brute_groups(texts) == {2: 1}


def test_groups_of_many_variants(spark):
    texts = _variants(14, 11)
    assert _groups(spark, texts, run_limit=3) == _brute_groups(texts)


def test_groups_in_rounds_and_cells(spark, monkeypatch):
    """Crowds cut into small cells and many rounds give the groups of brute force."""
    from semigrid.llm import shingle_sets

    monkeypatch.setattr(shingle_sets.crowd_pairs, "__defaults__", (3,))
    monkeypatch.setattr(simhash_dedup, "GROWTH", 3)
    common = _words(40, 99)
    texts = _variants(20, 12) + [_words(60, 200 + k) + " " + common for k in range(25)] + ["", None, "one", "One"]
    assert _groups(spark, texts, run_limit=2, hubs=2) == _brute_groups(texts)


@pytest.mark.parametrize("kind", ["appended", "scattered", "short", "block"])
def test_no_pair_over_the_similarity_is_missed(spark, kind):
    """Every kind of edit, by bands of similarity: all links of brute force, whatever their fingerprints."""
    r = random.Random(kind)
    texts = []
    for k in range(40):
        n = r.randint(8, 14) if kind == "short" else r.randint(60, 200)
        w = _words(n, 500 + k).split(" ")
        v = list(w)
        if kind in ("appended", "short"):
            v += _words(max(1, int(n * r.uniform(0.05, 0.3))), 900 + k).split(" ")
        elif kind == "scattered":
            for _ in range(r.randint(1, max(1, n // 40))):
                v[r.randrange(n)] = "new%d" % r.randrange(10**6)
        else:
            at, size = r.randrange(n), max(1, int(n * r.uniform(0.02, 0.12)))
            v[at : at + size] = _words(size, 1500 + k).split(" ")
        texts += [" ".join(w), " ".join(v)]
    want = _brute_groups(texts)
    assert _groups(spark, texts) == want and len(want) >= 5


def test_sketches_bound_differences():
    from semigrid.llm import shingle_sets as ss

    r = np.random.default_rng(0)
    for _ in range(200):
        both = r.integers(0, 2**63, r.integers(0, 400)).astype(np.uint64)
        x, y = (np.unique(np.r_[both, r.integers(0, 2**63, r.integers(0, 300)).astype(np.uint64)]) for _ in range(2))
        apart = len(np.setxor1d(x, y))
        p, q = ss.parity_sketch(x), ss.parity_sketch(y)
        assert ss.sketches_agree([p], [q], np.array([apart]))[0]
        near = len(np.intersect1d(x, y)) >= 0.8 * len(np.union1d(x, y))
        assert not near or ss.sketches_agree([p], [q], ss.most_apart(np.array([len(x)]), np.array([len(y)]), 0.8))[0]


def test_pipeline_row_for_row(spark, tmp_path):
    """Every stage against plain Python, on texts that each stage has to change."""
    near = _words(120, 31).split(" ")
    shared = _words(40, 32)
    texts = [" ".join(near), " ".join([*near[:60], "other", *near[61:]]), _words(90, 33), _words(90, 33), _words(30, 34) + " " + shared + " " + _words(30, 35), _words(50, 36) + " " + shared, "123 ²½", None, _words(20, 37)]
    rows = [(k, t, "aa" if k < 3 else None, "s", len(t or "")) for k, t in enumerate(texts)]
    spark.createDataFrame(rows, SCHEMA).write.parquet(str(tmp_path / "documents.parquet"))
    docs, states = spark.read.parquet(str(tmp_path / "documents.parquet")), []
    for _, stage in corpus_pipeline.STAGES[:-1]:
        docs = stage(spark, docs, str(tmp_path)).cache()
        states.append({r.doc_id: r for r in docs.collect()})
    assert {k for k in states[0]} == {0, 1, 2, 3, 4, 5, 8} and all(r.lang == "aa" for r in states[0].values())
    assert set(states[1]) == {0, 1, 2, 4, 5, 8} and set(states[2]) == set(states[3]) == {0, 2, 4, 5, 8}
    seen = set()
    for k in sorted(states[3]):
        raw = texts[k].encode()
        gone = np.zeros(len(raw), bool)
        for p in range(len(raw) - 99):
            if raw[p : p + 100] in seen:
                gone[p : p + 100] = True
            seen.add(raw[p : p + 100])
        assert states[3][k].text.encode() == bytes(np.frombuffer(raw, np.uint8)[~gone]) and states[3][k].n_chars == len(states[3][k].text)
    assert len(states[3][5].text) < len(texts[5])
    from tokenizers import Tokenizer

    tokenizer = Tokenizer.from_file(vocabulary("word_bpe_49k.json"))
    pieces = collections.defaultdict(int)
    for r in corpus_pipeline.run(spark, str(tmp_path)).collect():
        pieces[r.doc_id] += r.length
    assert dict(pieces) == {k: len(tokenizer.encode(x.text, add_special_tokens=False).ids) + 1 for k, x in states[3].items()}
