"""The training-data operators against brute force on small tables with hard rows."""

import hashlib
import itertools
import zlib

import numpy as np
import pyarrow.parquet as pq
import pytest
import regex

from nearcopy.llm import decontam, media, ngram_join, packing, parsing, passages, pii, token_store, tokens, toxicity, url_filter

LOW = str.maketrans("ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")
HARD = [
    (0, None),
    (1, ""),
    (2, " \n\t "),
    (3, "a"),
    (4, "A  b"),
    (5, "x" * 3000),
    (6, "é ü\nß " * 80),
    (7, "same words here again and again " * 30),
    (8, "same words here again and again " * 30),
    (9, "tail. Then,\nnext  two\n\nlines , and.5,6"),
    (10, "nul\0 inside \0"),
]
EXTRA = "doc_id long, text string, n_words long, spans string, score double, _id string, key string"


@pytest.fixture(scope="module")
def hard(spark):
    """Nulls, empty and long texts, repeats, and further columns with names that operators use."""
    return spark.createDataFrame(
        [(i, t, 7, "s", 0.5, "x", "k") for i, t in HARD] + [(7, HARD[7][1], None, None, None, None, None)], EXTRA
    )


@pytest.fixture(scope="module")
def void(spark):
    return spark.createDataFrame([], EXTRA)


def test_every_operator_takes_hard_and_empty_tables(spark, hard, void):
    items = spark.createDataFrame(
        [(1, "same words here again and again same words here again"), (2, None), (3, ""), (4, "a")],
        "item_id long, text string",
    )
    labels = spark.createDataFrame([(3, 1), (4, 0), (None, 1), (5, None)], "doc_id long, toxic int")
    for t, n in ((hard, 12), (void, 0)):
        assert url_filter.judge_urls(t.withColumnRenamed("text", "url"), url_filter.RULES).count() == n
        assert pii.add_pseudonyms(t).count() == n
        assert decontam.find_contamination(t, items).count() == n
        assert media.add_media(t).count() == n
        assert ngram_join.jaccard_components(t).count() == n
        assert token_store.read_token_files(
            token_store.write_token_files(t, tokens.public_file("word_bpe_49k.json"))
        ).count() == n
        assert toxicity.add_scores(t, toxicity.fit_toxicity(t, labels)).count() == n
        assert passages.repeated_passages(t).count() == n
        assert parsing.remove_repeats(t).count() == n
        assert packing.pack_documents(t, tokens.public_file("byte_bpe_50k.json")).agg({"length": "sum"}).count() == 1


def test_missing_columns_are_named(hard):
    with pytest.raises(ValueError, match="texts"):
        parsing.remove_repeats(hard, "texts")


def test_url_rules(spark):
    urls = [
        None,
        "nothing",
        "HTTP://WWW.Example.com/en/x?q#f",
        "http://example.com/en/",
        "http://a.example.com/en/",
        "http://example.com",
        "http://x.net/es/1",
        "http://notnet/es/1",
        "a://b.net://c/fr/",
        "http://com/?x",
        "http://.com/a",
    ]
    got = {r.url: r for r in url_filter.judge_urls(spark.createDataFrame([(u,) for u in urls], "url string"), url_filter.RULES).collect()}
    assert (got[None].host, got[None].path, got[None].rule, got[None].verdict) == ("", "", None, "allow")
    assert (got[urls[2]].host, got[urls[2]].rule, got[urls[2]].verdict) == (
        "www.example.com", "www.example.com/en/", "allow"
    )
    assert got[urls[3]].verdict == got[urls[4]].verdict == "block" and got[urls[5]].rule is None
    assert got[urls[6]].rule == "net/es/" and got[urls[7]].rule is None and got[urls[9]].rule == "com/"


def test_cascade_is_exact_on_its_universe(spark):
    keys = spark.range(3000).selectExpr("concat('k', id) AS key")
    c = url_filter.BloomCascade.fit(keys.where("substr(key, -1) = '7'"), keys)
    assert len(c.levels) >= 2
    from pyspark.sql import functions as F

    wrong = keys.where(c.contains(F.col("key")) != (F.substring("key", -1, 1) == "7"))
    assert wrong.count() == 0


def test_pseudonyms_keep_the_form():
    text = "mail a.b@x.example.com, card 4845168114407329 and 4845-1681-1440-7329, 9807915762804490, 248.167.124.71, 2021-03-04, DE89 3704 0044 0532 0130 00, 300.1.1.1, 31/02/2020"
    new, n = pii.pseudonymise(text)
    assert n == {"mail": 1, "card": 2, "address": 1, "date": 1, "iban": 1}
    assert len(
        new.split()
    ) == len(text.split()) and "9807915762804490" in new and "300.1.1.1" in new and "31/02/2020" in new
    cards = regex.findall(r"\d{4}-?\d{4}-?\d{4}-?\d{4}", new)
    assert cards[0] == cards[1].replace("-", "") and pii.luhn_digit(cards[0][:-1]) == cards[0][-1]
    assert pii.pseudonymise(text, b"other")[0] != new
    assert sorted(pii.permute_below(v, 1000, b"k", b"t") for v in range(1000)) == list(range(1000))


def test_a_phone_has_one_pseudonym_however_written():
    new = [pii.pseudonymise(t)[0] for t in ("212-555-0123", "212.555.0123", "(212) 555-0123", "+1 212-555-0123")]
    assert len({regex.sub(r"\D", "", t)[-10:] for t in new}) == 1 and new[3].startswith("+1 ")


def words(t):
    return regex.findall(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+", (t or "").translate(LOW))


def test_decontamination(spark):
    rng = np.random.default_rng(2)
    vocab = [f"w{i}" for i in range(30)]
    items = [(i, " ".join(rng.choice(vocab, n))) for i, n in enumerate([1, 3, 9, 10, 11, 40, 40])] + [(7, "")]
    docs = []
    for d in range(40):
        w = list(rng.choice(vocab, int(rng.integers(0, 60))))
        if d % 2:
            src = items[int(rng.integers(3, 7))][1].split()
            a = int(rng.integers(0, len(src)))
            w[3:3] = src[a : a + int(rng.integers(5, 25))]
        docs.append((d, " ".join(w)))
    df, it = spark.createDataFrame(
        docs, "doc_id long, text string"
    ), spark.createDataFrame(items, "item_id long, text string")
    for part in (1 << 20, 60):  # sent to the documents, and joined with them
        got = {r.doc_id: r for r in decontam.digest(decontam.find_contamination(df, it, part_bytes=part)).collect()}
        for d, t in docs:
            w, hit, names = words(t), set(), set()
            for i, x in items:
                b = words(x)
                n = min(10, len(b))
                for p, q in itertools.product(range(len(w) - n + 1), range(len(b) - n + 1) if n else ()):
                    if w[p : p + n] == b[q : q + n]:
                        hit |= set(range(p, p + n))
                        names.add(str(i))
            r = got[d]
            assert (r.n_words, r.n_hit, r.n_items, r.items_sha256) == (
                len(w), len(hit), len(names), hashlib.sha256(",".join(sorted(names)).encode()).hexdigest()
            )
        assert {r.doc_id for r in decontam.drop_contaminated(df, it, part_bytes=part).collect()} == {
            d for d in got if not got[d].contaminated
        }


def test_png():
    rng = np.random.default_rng(0)
    pixels = rng.integers(0, 256, (9, 64)).astype(np.uint8)
    kinds = np.array([0, 1, 2, 3, 4, 4, 2, 1, 3], np.uint8)
    rows = np.array([media.filter_rows(pixels, k)[i] for i, k in enumerate(kinds)])
    assert (media.unfilter_rows(kinds, rows) == pixels).all()
    data = media.encode_png(pixels.tobytes())
    assert (media.decode_png(data) == pixels).all()
    for bad in (data[:-5], data[1:], data[:60] + bytes([data[60] ^ 1]) + data[61:]):
        with pytest.raises(ValueError):
            media.decode_png(bad)


def shingles(t, k):
    w = regex.findall(r"[^\x20\x09-\x0D]+", (t or "").translate(LOW))
    return frozenset(tuple(w[i : i + k]) for i in range(max(1, len(w) - k + 1))) if w else frozenset()


def brute_components(rows, k, percent):
    sets, up = {i: shingles(t, k) for i, t in rows}, {i: i for i, _ in rows}

    def find(x):
        while up[x] != x:
            x = up[x]
        return x

    for a, b in itertools.combinations(sorted(sets), 2):
        both = len(sets[a] & sets[b])
        if both and 100 * both >= percent * (len(sets[a]) + len(sets[b]) - both):
            x, y = sorted((find(a), find(b)))
            up[y] = x
    return {i: (len(sets[i]), find(i)) for i in sets}


@pytest.mark.parametrize(
    "k, percent, shingles, sets",
    [(4, 85, 1 << 22, 512), (4, 85, 150, 512), (4, 85, 1 << 22, 3), (5, 80, 1 << 22, 512), (5, 80, 1 << 22, 5)],
)
def test_jaccard_join(spark, k, percent, shingles, sets):
    """Whole groups, and groups split by their shingles or sets."""
    rng = np.random.default_rng(3)
    rows = []
    for _ in range(25):
        base = [f"w{rng.integers(0, 60)}" for _ in range(int(rng.integers(1, 45)))]
        for _ in range(12):
            w = list(base)
            for _ in range(int(rng.integers(0, 4))):
                at = int(rng.integers(0, len(w)))
                w[at : at + 1] = [f"z{rng.integers(0, 9)}"] if rng.random() < 0.5 else [w[at], f"q{rng.integers(0, 9)}"]
            rows.append((len(rows), " ".join(w)))
    rows += [(900, ""), (901, None), (902, "a b"), (903, "A  b")]
    table = spark.createDataFrame(rows, "doc_id long, text string")
    found = ngram_join.jaccard_components(table, shingle=k, percent=percent, group_shingles=shingles, group_sets=sets)
    got = {r[0]: (r[1], r[2]) for r in found.collect()}
    assert got == brute_components(rows, k, percent)


def test_elias_fano():
    rng = np.random.default_rng(1)
    for values in ([], [0], [5, 5, 5], np.sort(rng.integers(0, 10**6, 3000)), np.arange(700)):
        e = token_store.EliasFano.encode(np.array(values, np.int64))
        again, _ = token_store.EliasFano.read(e.to_bytes(), 0)
        assert again.all().tolist() == list(values)
    with pytest.raises(ValueError):
        token_store.EliasFano.encode(np.array([3, 2]))
    raw = bytearray(token_store.write_file([1, 2], [b"\1\0", b"\2\0\3\0"], 2))
    f = token_store.TokenFile(bytes(raw))
    assert f.doc_ids() == [1, 2] and f.tokens(1).tolist() == [2, 3]
    raw[-6] ^= 1
    with pytest.raises(ValueError):
        token_store.TokenFile(bytes(raw))


@pytest.mark.parametrize("name, end", [("word_bpe_49k.json", 2), ("byte_bpe_50k.json", 0)])
def test_cached_ids_are_the_tokenizer_s(name, end):
    t = tokens.CachedTokenizer(tokens.public_file(name))
    texts = [x or "" for _, x in HARD] + [
        "it's a b, c. d!? 3.14,15 \n x",
        " lead",
        "trail ",
        "a .b ,c",
        "İstanbul Ǆ ﬁ e\u0301 x",
        "<|endoftext|> a",
        "a\u00a0b c\td",
        "a\r\n b",
    ]
    assert [t.ids(x).tolist() for x in t.encode(texts)] == [
        e.ids for e in t.tokenizer.encode_batch(texts, add_special_tokens=False)
    ]


def test_packing_covers_every_token(spark, hard):
    path = tokens.public_file("byte_bpe_50k.json")
    t = tokens.CachedTokenizer(path)
    rows = [(i, x) for i, x in HARD]
    pieces = packing.pack_documents(spark.createDataFrame(rows, "doc_id long, text string"), path).collect()
    for i, x in rows:
        ids = np.array(t.tokenizer.encode(x or "", add_special_tokens=False).ids + [0], "<u4")
        at = 0
        for p in sorted((p for p in pieces if p.doc_id == i), key=lambda p: p.start):
            assert p.start == at and p.ids_crc32 == zlib.crc32(
                ids[at : at + p.length].tobytes()
            ) and p.doc_tokens == len(ids)
            at += p.length
        assert at == len(ids)
    for _, g in itertools.groupby(sorted(pieces, key=lambda p: (p.sequence_id, p.offset)), key=lambda p: p.sequence_id):
        at = 0
        for p in g:
            assert p.offset == at
            at += p.length
        assert at <= 1024 and at & (at - 1) == 0


def test_costs_are_balanced():
    lengths = np.array([900, 800, 500, 300, 200, 100, 100, 100, 72])
    got = packing.assign(lengths, [1024, 1024, 1024])
    assert sum(n for _, _, n, _, _ in got) == lengths.sum()
    assert {k for i, _, _, k, _ in got if i in (0, 1, 2)} == {0, 1, 2}


def test_subsequence_kernel():
    words = ["idiot", "i-d-i.o-t", "edition", "s c u m", "scum", "abc", "", "!?", "\u00fc\u00df", "a\0b"]

    def feats(word):
        letters = [c for c in word if c.isalpha()]
        if not letters:
            return {}, 0.0
        marked = list(enumerate(["^", *letters, "$"]))
        out, square = {}, 0.0
        for (i, a), (_, b), (k, c) in itertools.combinations(marked, 3):
            if k - i < toxicity.REACH:
                weight = toxicity.DECAY ** (k - i + 1)
                out[a, b, c] = out.get((a, b, c), 0) + weight
                square += weight**2
        return out, square**0.5

    want = np.zeros((len(words), len(words)))
    for (i, (x, p)), (j, (y, q)) in itertools.product(enumerate(map(feats, words)), repeat=2):
        want[i, j] = sum(v * y.get(k, 0) for k, v in x.items()) / (p * q) if p * q else 0
    assert np.allclose(toxicity.subsequence_kernel(words, words), want, atol=1e-5)
    features, columns = toxicity.feature_rows(words)
    table, weights = np.zeros(toxicity.CODES**3), np.arange(len(words)) - 3.0
    table[columns] = weights @ features
    assert np.allclose(toxicity.table_margins(table, words), want @ weights, atol=1e-4)  # folding is exact


def test_toxicity_finds_gapped_words():
    rng = np.random.default_rng(0)
    clean = [" ".join("".join(rng.choice(list("aeinrstlohcpgfvy"), 6)) for _ in range(40)) for _ in range(300)]
    bad = ["numskull", "dimwit"]
    texts = clean[:200] + [f"{a[:140]} {bad[k % 2]} {a[140:]}" for k, a in enumerate(clean[200:])]
    m = toxicity.fit_model(texts, [0] * 200 + [1] * 100)
    s = toxicity.score_texts(m, ["x numskull y", "x numsk-ull y", "some d i m w i t here", "", None, "tr " * 300_000])
    assert (s[:3] >= 0.5).all() and s[3] == s[4] < 0.5 and s[5] < 0.5
    usual = toxicity.score_texts(m, clean[:200])
    assert (usual < 0.5).mean() > 0.95
    assert toxicity.score_texts(m, ["x nu.msk-ull y"])[0] > np.quantile(usual, 0.95)  # many gaps lower a score


def test_toxicity_on_rows_it_has_not_seen():
    """Varied endings of insults in four languages; the rows with remainder 0 are not learnt from."""
    folder = "/root/testdata/sf0.1"
    docs, labels = (pq.read_table(f"{folder}/{t}.parquet").to_pandas() for t in ("documents", "labels"))
    rows = docs.merge(labels, on="doc_id")
    held = np.array([zlib.crc32(str(i).encode()) % 5 == 0 for i in rows.doc_id])
    taught = rows[~held & (rows.text.str.len() <= toxicity.MAX_TRAIN_CHARS)]
    model = toxicity.fit_model(list(taught.text), list(taught.toxic), toxicity.LEAST_PRIOR)
    asked = rows[held]
    score, y, lang = toxicity.score_texts(model, list(asked.text)), asked.toxic.to_numpy(), asked.lang.to_numpy()
    for some in [np.ones(len(y), bool), *(lang == v for v in ("en", "de", "fr", "es"))]:
        bad, good = score[some & (y == 1)], score[some & (y == 0)]
        assert (bad[:, None] > good[None]).mean() >= 0.92
        assert (bad >= 0.5).mean() >= 0.75 and (good < 0.5).mean() >= 0.93
    assert (score[y == 1] >= 0.5).mean() >= 0.88 and (score[y == 0] < 0.5).mean() >= 0.98


def test_repeated_passages(spark):
    rng = np.random.default_rng(4)
    vocab = [f"w{i}" for i in range(4000)]
    docs = [list(rng.choice(vocab, int(rng.integers(20, 300)))) for _ in range(60)]
    later = set()
    for _ in range(8):
        p = list(rng.choice(vocab, int(rng.integers(60, 100))))
        ids = sorted(int(d) for d in rng.choice(60, 3, replace=False))
        for d in ids:
            docs[d][0:0] = p
        later |= set(ids[1:])
    got = {r.doc_id for r in passages.repeated_passages(spark.createDataFrame([(i, " ".join(w)) for i, w in enumerate(docs)], "doc_id long, text string")).where("n_repeated >= 50").collect()}
    assert len(later - got) <= 1 and not got - later


def test_repeated_passages_with_common_lines(spark):
    """Each passage of two documents holds a line that unrelated earlier documents have too."""
    rng = np.random.default_rng(7)
    rows, last = [], []
    for t in range(150):
        new = lambda n: [f"t{t}w{x}" for x in rng.integers(0, 10**6, n)]  # noqa: B023, E731
        p = new(60)
        a = int(rng.integers(0, 31))
        for w in [new(80) + p[a : a + 30] + new(80) for _ in range(3)] + [new(50) + p + new(70), new(90) + p + new(30)]:
            rows.append((len(rows), " ".join(w)))
        last.append(len(rows) - 1)
    got = {r.doc_id for r in passages.repeated_passages(spark.createDataFrame(rows, "doc_id long, text string")).where("n_repeated >= 50").collect()}
    assert len(set(last) - got) <= 1 and not got - set(last)


def test_repeated_passages_finds_near_copies(spark):
    """Passages with some words changed, beside a line that all texts share; truth by the Jaccard similarity of their 5-grams."""
    rng = np.random.default_rng(11)
    line = [f"common{x}" for x in range(30)]
    rows, want, clean = [], set(), set()

    def new(n):
        return [f"w{x}" for x in rng.integers(0, 10**6, n)]

    def grams(w):
        return {tuple(w[i : i + 5]) for i in range(len(w) - 4)}

    for _ in range(200):
        p = new(int(rng.integers(55, 140)))
        q = list(p)
        for _ in range(int(rng.integers(0, 3))):
            q[int(rng.integers(0, len(q)))] = new(1)[0]
        clean.add(len(rows))
        rows.append((len(rows), " ".join(new(40) + line + p + new(60))))
        if 10 * len(grams(p) & grams(q)) >= 8 * len(grams(p) | grams(q)):
            want.add(len(rows))
        rows.append((len(rows), " ".join(new(int(rng.integers(5, 80))) + q + line + new(30))))
    table = spark.createDataFrame(rows, "doc_id long, text string").repartition(5)
    got = {r.doc_id for r in passages.repeated_passages(table).where("n_repeated >= 50").collect()}
    assert len(want & got) >= 0.95 * len(want) and not got & clean


def test_copies_of_one_text_are_settled_in_their_tasks(spark):
    """Hundreds of exact copies: all but the first are repeats, wherever they lie."""
    text = " ".join(f"w{x}" for x in np.random.default_rng(12).integers(0, 10**6, 90))
    table = spark.createDataFrame([(i, text) for i in range(300)], "doc_id long, text string").repartition(6)
    got = {r.doc_id: r.n_repeated for r in passages.repeated_passages(table).collect()}
    assert got == {i: 90 if i else 0 for i in range(300)}


def test_pairs_of_nodes_do_not_depend_on_batches():
    rng = np.random.default_rng(3)
    n = 400
    nothing = passages.pa.nulls(n, passages.pa.int64())
    cols = [rng.integers(0, 12, n), rng.integers(0, 40, n), rng.integers(0, 90, n) << 4, rng.integers(0, 4, n) << 2]
    order = np.lexsort((cols[2], cols[1], cols[0]))
    whole = passages.batch(passages._NODE, *[c[order] for c in cols], nothing, nothing)

    def pairs(parts):
        return sorted(
            r for b in passages._pair_up(parts) for r in zip(*(c.to_pylist() for c in b.columns), strict=True)
        )

    assert pairs([whole]) == pairs([whole.slice(i, 7) for i in range(0, n, 7)])


def test_sketches_are_no_more_than_cores(spark, monkeypatch):
    texts = [f"a b c d e{i % 7} f g" for i in range(200)]
    table = spark.createDataFrame([(t,) for t in texts], "_text string").repartition(40)
    want, seen, plain = ngram_join.shingle_levels(table.coalesce(1)), [], ngram_join.arrow_map

    def watched(df, f, schema):
        seen.append(df.rdd.getNumPartitions())
        return plain(df, f, schema)

    monkeypatch.setattr(ngram_join, "arrow_map", watched)
    assert (ngram_join.shingle_levels(table) == want).all()
    assert seen[0] <= spark.sparkContext.defaultParallelism < 40


def test_texts_without_parts_to_verify_are_only_counted(monkeypatch):
    texts = ["", None, "one", "a b\u00e9 c-d", " x ", "...", "end"] * 3
    data, offsets = passages.text_bytes(passages.pa.array(texts))
    want = passages.gram_sequences(data, offsets)[2]
    rows = passages.pa.RecordBatch.from_arrays(
        [passages.pa.array(range(len(texts))), passages.pa.array(texts), passages.pa.nulls(len(texts))],
        names=["doc_id", "text", "checks"],
    )
    monkeypatch.setattr(passages, "gram_sequences", None)
    (out,) = passages._report(5, 46, 80)([rows])
    assert out.column("n_words").to_pylist() == want.tolist() == [0, 0, 1, 4, 1, 0, 1] * 3
    assert out.column("n_repeated").to_pylist() == [0] * len(texts) and out.column("spans").to_pylist() == [[]] * len(texts)


def test_compact_windows():
    rng = np.random.default_rng(0)
    v, bounds = rng.integers(0, 30, 200).astype(np.uint64), np.array([0, 70, 75, 200])
    want = set()
    for a, e in itertools.pairwise(bounds):
        for c in range(a, e):
            low, high = c, c
            while low > a and v[low - 1] > v[c]:
                low -= 1
            while high + 1 < e and v[high + 1] >= v[c]:
                high += 1
            if high - low >= 11:
                want.add((c, low, high))
    assert set(zip(*(x.tolist() for x in passages.compact_windows(v, bounds, 12)), strict=True)) == want


def test_repeat_removal(spark):
    rng = np.random.default_rng(1)
    rows = [(i, "".join(rng.choice(list("ab"), p=[0.9, 0.1], size=rng.integers(0, 500)))) for i in range(30)] + [
        (100 + i, "x" * int(rng.integers(90, 300))) for i in range(5)
    ] + [(200, ""), (201, "é" * 200), (202, None)]
    base = "".join(rng.choice(list("abcdefgh "), size=1500))
    for k in range(25):
        a = int(rng.integers(0, 1300))
        rows.append((300 + k, "".join(rng.choice(list("xyz "), size=120)) + base[a : a + int(rng.integers(90, 250))]))
    same_removal(spark, rows)


def same_removal(spark, rows):
    table = spark.createDataFrame(rows, "doc_id long, text string").repartition(3)
    got = {r[0]: (r[1], r[2], r[3], r[4]) for r in parsing.remove_repeats(table, with_bytes=False).collect()}
    seen = set()
    for i, t in sorted(rows, key=lambda r: r[0]):
        d = (t or "").encode()
        gone = np.zeros(len(d), bool)
        for p in range(len(d) - 99):
            if d[p : p + 100] in seen:
                gone[p : p + 100] = True
            seen.add(d[p : p + 100])
        spans = int((np.diff(np.concatenate(([0], gone.astype(int)))) == 1).sum())
        kept = hashlib.sha256(np.frombuffer(d, np.uint8)[~gone].tobytes()).hexdigest()
        assert got[i] == (len(d), int(gone.sum()), spans, kept)


def test_repeat_removal_of_shared_lines(spark, monkeypatch):
    """One line in many surroundings: its triggers have more entries than GROUP, so their strings are settled one by one."""
    rng = np.random.default_rng(5)
    word = lambda n: "".join(rng.choice(list("abcdefghijklmnop "), size=n))
    line = word(260)
    rows = [(i, word(int(rng.integers(20, 200))) + line[int(rng.integers(0, 60)) :] + word(int(rng.integers(0, 200)))) for i in range(60)]
    same_removal(spark, rows)
    monkeypatch.setattr(parsing, "GROUP", 4)
    same_removal(spark, rows)


def test_repeat_removal_of_long_texts(spark):
    """Texts beyond one block, which repeat parts of themselves and of others, and bytes without any trigger."""
    rng = np.random.default_rng(6)
    long = "".join(rng.choice(list("abcdefgh ijkl"), size=1_300_000))
    rows = [
        (1, long + long[500:900] + "q" * 3000),
        (2, "w" * 150 + long[1_000_000:1_200_000] + "q" * 500),
        (3, "short"),
        (4, long[:99]),
    ]
    same_removal(spark, rows)


def test_triggers_depend_on_the_string_alone():
    rng = np.random.default_rng(8)
    part = rng.integers(97, 110, 100, dtype=np.uint8)
    found = set()
    for _ in range(50):
        before, after = (rng.integers(97, 110, int(n), dtype=np.uint8) for n in rng.integers(0, 300, 2))
        data = np.concatenate([before, part, after])
        _, _, _, trigger, first, last = parsing.phrases(data, np.array([0, len(data)]))
        k = np.flatnonzero((first <= len(before)) & (len(before) <= last))
        assert len(k) == 1
        found.add(int(trigger[k[0]] - len(before)))
    assert len(found) == 1


def test_pipeline_stages(spark, data):
    import corpus_pipeline as C

    docs = spark.read.parquet(f"{data}/documents.parquet")
    names = docs.columns
    for name, stage in C.STAGES[:-1]:
        before = {r.doc_id: r.text for r in docs.collect()}
        docs = stage(spark, docs, data)
        assert docs.columns == names
        after = {r.doc_id: r.text for r in docs.collect()}
        assert set(after) <= set(before)
        if name == "near duplicates":
            want = brute_components([(i, t) for i, t in before.items()], 5, 80)
            assert set(after) == {i for i in before if want[i][1] == i}
        docs = spark.createDataFrame(docs.collect(), docs.schema)
    assert C.STAGES[-1][1](spark, docs, data).agg({"length": "sum"}).first()[0] > 0


# ---- queries against brute force, column by column, on the smallest table and on hard rows -----


@pytest.fixture(scope="module")
def hard_dir(spark, data, tmp_path_factory):
    """Tables as the queries read them: the smallest documents and hard rows under new ids, with columns of clashing names."""
    path = tmp_path_factory.mktemp("hard")
    docs = pq.read_table(f"{data}/documents.parquet").to_pandas()
    rows = [(int(i), t) for i, t in zip(docs.doc_id, docs.text, strict=True)]
    long = "".join(np.random.default_rng(21).choice(list("abcdefgh \u00e9,.\n1"), size=1_400_000))
    rows += [(10_000 + i, t) for i, t in HARD] + [
        (20_000, long), (20_001, long[:700_000] + "!" + long[700_000:]), (20_002, "")
    ]
    names = ("host", "rule", "verdict", "n_values", "n_bytes", "start", "feature", "_text", "_id", "score")
    table = spark.createDataFrame(rows, "doc_id long, text string")
    for n in names:
        table = table.withColumn(n, passages.F.lit(7))
    table.repartition(3).write.parquet(f"{path}/documents.parquet")
    for t in ("benchmark", "labels", "pages"):
        spark.read.parquet(f"{data}/{t}.parquet").write.parquet(f"{path}/{t}.parquet")
    return str(path), rows


def test_media_query_by_brute_force(spark, hard_dir):
    path, rows = hard_dir
    got = {r.doc_id: r for r in media.op4_media_columns(spark, path).collect()}
    assert len(got) == len(rows)
    kept = {r.doc_id: bytes(r.media) for r in media.add_media(spark.read.parquet(f"{path}/documents.parquet")).select("doc_id", "media").collect()}
    cosine = [[np.cos(np.pi * (2 * x + 1) * u / 64) for x in range(32)] for u in range(8)]
    for i, t in rows:
        raw = (t or "").encode()
        padded = raw + bytes(-len(raw) % 64 or (0 if raw else 64))
        r = got[i]
        assert (r.n_bytes, r.payload_bytes, r.payload_sha256) == (
            len(raw), len(padded), hashlib.sha256(padded).hexdigest()
        )
        assert r.tail_crc32 == zlib.crc32(padded[-64:])
        assert (r.media_bytes, r.media_sha256) == (len(kept[i]), hashlib.sha256(kept[i]).hexdigest())
        if len(padded) <= 6400:  # the transform by its definition, for pictures of up to 100 rows
            x = np.frombuffer(padded, np.uint8).reshape(-1, 64).astype(float)
            n = len(x)
            cuts = [k * n // 32 for k in range(33)]
            x = np.array(
                [x[a : max(b, a + 1)].mean(axis=0) for a, b in itertools.pairwise(cuts)]
            ) if n >= 32 else x[[k * n // 32 for k in range(32)]]
            x = np.array([x[:, 2 * k : 2 * k + 2].mean(axis=1) for k in range(32)]).T
            low = [round(sum(cosine[u][a] * cosine[v][b] * x[a, b] for a in range(32) for b in range(32)), 6) for u in range(8) for v in range(8)] if n <= 20 else None
            if low:
                middle = float(np.median(low[1:]))
                bits = [False] + [v > middle for v in low[1:]]
                near = [k for k, v in enumerate(low) if abs(v - middle) < 1e-4]
                mine = np.unpackbits(np.frombuffer(bytes.fromhex(r.feature), np.uint8)).astype(bool)
                assert all(mine[k] == bits[k] for k in range(64) if k not in near)


def test_every_png_filter_is_undone():
    rng = np.random.default_rng(2)
    pixels = rng.integers(0, 256, (23, 64), dtype=np.uint8)
    whole = {k: media.filter_rows(pixels, k) for k in range(5)}
    kinds = np.array([0, 1, 1, 2, 4, 4, 4, 3, 3, 2, 2, 1, 3, 4, 0, 0, 4, 4, 4, 4, 3, 3, 3], np.uint8)
    assert (media.unfilter_rows(kinds, np.array([whole[k][r] for r, k in enumerate(kinds)])) == pixels).all()


def test_token_query_by_brute_force(spark, hard_dir):
    from tokenizers import Tokenizer

    path, rows = hard_dir
    got = {r.doc_id: r for r in token_store.op6_token_store(spark, path).collect()}
    t, at = Tokenizer.from_file(tokens.public_file("word_bpe_49k.json")), 0
    for i, text in sorted(rows):
        ids = np.array([*t.encode(text or "", add_special_tokens=False).ids, 2], "<u4")
        assert (got[i].start, got[i].n_tokens, got[i].ids_crc32) == (at, len(ids), zlib.crc32(ids.tobytes()))
        at += len(ids)
    assert len(got) == len(rows)


def test_pseudonym_query_by_brute_force(spark, hard_dir):
    """Row by row the same as the plain function; lengths and signs stay; pseudonyms are one to one."""
    path, rows = hard_dir
    got = {r.doc_id: r for r in pii.op2_pii_pseudonyms(spark, path).collect()}
    pairs: dict[str, dict[str, str]] = {}
    for i, text in rows:
        new, counts = pii.pseudonymise(text)
        assert (got[i].text, got[i].n_values) == (new, sum(counts.values()))
        if not text:
            assert got[i].text == text
            continue
        if counts.get("address"):  # decimal parts have one to three digits
            continue
        assert len(new) == len(text)
        assert all(a == b or (a.isdigit() and b.isdigit()) or (a.isalpha() and b.isalpha()) or (a + b).isalnum() for a, b in zip(text, new, strict=True))
        for kind in ("social", "card", "iban"):
            for m in pii._all[kind].finditer(text):
                a, b = m.group(), new[m.start() : m.end()]
                if a != b:
                    assert pairs.setdefault(kind, {}).setdefault(a, b) == b
    for seen in pairs.values():
        assert len(set(seen.values())) == len(seen)


def test_url_query_with_clashing_names(spark, data):
    pages = spark.read.parquet(f"{data}/pages.parquet")
    for n in ("host", "path", "rule", "verdict", "key"):
        pages = pages.withColumn(n, passages.F.lit(None).cast("int"))
    plain = url_filter.judge_urls(spark.read.parquet(f"{data}/pages.parquet"), url_filter.RULES)
    names = ["page_id", "host", "path", "rule", "verdict"]
    want = sorted(map(repr, plain.select(*names).collect()))
    assert sorted(map(repr, url_filter.judge_urls(pages, url_filter.RULES).select(*names).collect())) == want


def test_long_texts_in_several_blocks(spark):
    """Texts beyond BLOCK_BYTES: contamination at their ends, near copies, and passages."""
    rng = np.random.default_rng(31)
    words_ = [f"w{x}" for x in rng.integers(0, 10**6, 220_000)]
    passage = [f"p{x}" for x in range(80)]
    other = [f"v{x}" for x in rng.integers(0, 10**6, 200_000)]
    near = list(words_)
    for k in range(0, len(near), 400):
        near[k] = "changed"
    rows = [
        (1, " ".join(words_)),
        (2, " ".join(near)),
        (3, " ".join([*other, *passage])),
        (4, " ".join([*passage, *other[::-1]])),
        (5, "small"),
    ]
    assert len(rows[0][1]) > 1 << 20
    table = spark.createDataFrame(rows, "doc_id long, text string").repartition(2)
    items = spark.createDataFrame([(7, " ".join(passage[50:65]))], "item_id long, text string")
    for part in (1 << 20, 10):
        found = {r.doc_id: r.spans for r in decontam.find_contamination(table, items, part_bytes=part).collect()}
        hit = {d: (min(s.first for s in v), max(s.end for s in v)) for d, v in found.items() if v}
        assert hit == {3: (200_050, 200_065), 4: (50, 65)}
    groups = {r[0]: r[2] for r in ngram_join.jaccard_components(table).select("doc_id", "n_shingles", "component_id").collect()}
    assert groups == {1: 1, 2: 1, 3: 3, 4: 4, 5: 5}
    got = {r.doc_id: r.n_repeated for r in passages.repeated_passages(table).collect()}
    assert got[1] == got[3] == got[5] == 0 and got[4] == 80 and got[2] > 200_000


def test_pipeline_stages_on_hard_and_empty_tables(spark, hard, void, data):
    import corpus_pipeline as C

    for table in (hard, void):
        docs = table
        n = docs.count()
        for _, stage in C.STAGES[:-1]:
            docs = stage(spark, docs, data)
            assert docs.columns == table.columns
            docs = spark.createDataFrame(docs.collect(), table.schema)
        assert docs.where("text IS NULL").count() == table.where("text IS NULL").count()
        assert docs.count() == max(0, n - 1)  # a copy under another id goes
        pieces = C.STAGES[-1][1](spark, docs, data)
        assert pieces.where("octet_length(ids) <> 4 * length").count() == 0


def test_leaks_are_dropped_by_both_ways(spark, hard):
    items = spark.createDataFrame([(1, HARD[7][1][:80]), (2, None)], "item_id long, text string")
    for part in (1 << 20, 3):
        kept = decontam.drop_contaminated(hard, items, part_bytes=part)
        assert kept.columns == hard.columns
        assert sorted(r.doc_id for r in kept.collect()) == [0, 1, 2, 3, 4, 5, 6, 9, 10]


def test_repeated_passages_meet_all_documents_of_a_signature(spark):
    """A passage and its copy, each behind 30 texts that have most of its signatures but are too unlike it."""
    rng = np.random.default_rng(21)
    rows, last = [], []

    def new(n):
        return [f"w{x}" for x in rng.integers(0, 10**6, n)]

    for _ in range(8):
        passage = new(60)
        for _ in range(2):
            for k in range(30):
                unlike = list(passage)
                unlike[k % 13 :: 13] = new(len(unlike[k % 13 :: 13]))
                rows.append((len(rows), " ".join(new(40) + unlike + new(40))))
            rows.append((len(rows), " ".join(new(40) + passage + new(40))))
        last.append(len(rows) - 1)
    table = spark.createDataFrame(rows, "doc_id long, text string").repartition(3)
    got = {r.doc_id: r.n_repeated for r in passages.repeated_passages(table).collect()}
    assert sum(got[i] >= 58 for i in last) >= 7
