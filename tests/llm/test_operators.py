"""Text-preparation operators against their SQL, brute force, or libraries; and their results on odd inputs."""

import collections
import hashlib
import zlib

import numpy as np
import pandas as pd
import pytest
import xxhash
from pyspark.sql import functions as F

from tests.conftest import FULL, check_query
from tilestar.llm import bpe, components, html, licenses, linededup, neighbours, packing, quality, registry, simhash, substring, toxicity, wordhash
from tilestar.runtime import Scratch

QUERIES, ORACLES = registry.queries(), registry.oracle_sql()
SCHEMA = "doc_id bigint, text string, lang string, source string, n_chars bigint, n_words bigint"
LONG = " ".join(f"w{k % 977}x{k % 13}" for k in range(30_000))
PASSAGE = " ".join(f"p{k}" for k in range(60))
ODD = [
    (1, None, None, None, None, 5), (2, "", "en", "s", 0, None), (3, " \t\n ", None, "s", 4, 1), (4, "one two three", "en", None, 13, 1), (5, "one two three", "en", None, 13, 1),
    (6, LONG, "en", "s", len(LONG), 1), (7, f"a b {PASSAGE} tail", "en", "s", 1, 1), (8, f"other {PASSAGE}", "en", "s", 1, 1), (9, "line number one is here now\nline number one is here too", "en", "s", 1, 1),
    (9, "line number one is here now\nline number one is here too", "en", "s", 1, 1), (10, "Line number one is here now", "en", "s", 1, 1), (11, "café 日本語 🙂 <|endoftext|> x", "fr", "s", 1, 1), (None, "no id at all", "en", "s", 1, 1),
]


@pytest.fixture(scope="module")
def odd(spark):
    return spark.createDataFrame(ODD, SCHEMA)


@pytest.fixture(scope="module")
def documents(spark):
    return spark.read.parquet(f"{FULL}/documents.parquet")


def texts_of(df):
    return [(r["doc_id"], r["text"]) for r in df.select("doc_id", "text").collect()]


@pytest.mark.parametrize("name", sorted(ORACLES))
def test_equals_sql(spark, duck, name):
    check_query(spark, duck, QUERIES, ORACLES, name)


@pytest.mark.parametrize("f", [quality.op1_quality, linededup.op4_line_dedup, bpe.op5_bpe, simhash.op6_simhash, licenses.op7_licenses, substring.op9_substring_dedup])
def test_odd_and_empty_tables(odd, f):
    assert f(odd).count() == len(ODD)
    assert f(odd.limit(0)).count() == 0


# quality


def test_ledger_and_ablation(odd):
    led = {r["doc_id"]: r for r in quality.op1_quality(odd).collect()}
    assert led[1]["n_words"] == 0 and led[1]["base_failed"] and not led[1]["kept"]
    assert led[6]["n_words"] == 30_000 and led[6]["n_repeat_words"] == 30_000 and led[6]["base_failed"]
    assert not led[7]["base_failed"]
    rows = {r["rule"]: r for r in quality.ablation(quality.ledger(odd.select("doc_id", "text"))).collect()}
    assert rows["too_few_words"]["n_failed"] >= 9 and rows["repeated_windows"]["n_only"] == 1
    assert quality.keep(odd).columns == odd.columns


def test_repeated_windows_by_brute_force(spark):
    rng = np.random.default_rng(3)
    texts = [" ".join(rng.choice(list("ab"), n)) for n in (7, 8, 9, 40, 300)]
    df = spark.createDataFrame(list(enumerate(texts)), "doc_id bigint, text string")
    for r in quality.op1_quality(df).collect():
        w = texts[r["doc_id"]].split()
        n = collections.Counter(tuple(w[i : i + 8]) for i in range(len(w) - 7))
        assert r["n_repeat_words"] == len({i + j for i in range(len(w) - 7) if n[tuple(w[i : i + 8])] > 1 for j in range(8)})


# toxicity


def test_toxicity_on_held_out_documents(spark):
    got = QUERIES["op2_toxicity"](spark, "/root/testdata/sf0.1").toPandas()
    rows = got.merge(pd.read_parquet("/root/testdata/sf0.1/labels.parquet"), on="doc_id")
    rows = rows[rows.held_out]
    rank, positive = rows.score.rank(), rows.toxic.sum()
    auc = (rank[rows.toxic == 1].sum() - positive * (positive + 1) / 2) / (positive * (len(rows) - positive))
    assert auc > 0.95 and got.score.between(0, 1).all()
    assert all((zlib.crc32(str(r.doc_id).encode()) % 4 == 2) == r.held_out for r in got.head(200).itertuples())


def test_kernel_tolerates_gaps():
    near = toxicity.kernel(["id-iot", "i.diot", "idiiot", "window"], ["idiot"])[:, 0]
    assert near[:3].min() > 4 * near[3]


def test_toxicity_without_labels(spark, odd):
    none = spark.createDataFrame([], "doc_id bigint, quality int, toxic int")
    rows = toxicity.op2_toxicity(odd, none).collect()
    assert len(rows) == len(ODD) and {r["score"] for r in rows} == {0.0}
    one = spark.createDataFrame([(4, 1, 1), (5, 1, None), (None, 1, 1), (6, 1, 1)], "doc_id bigint, quality int, toxic int")
    assert toxicity.op2_toxicity(odd, one).count() == len(ODD)
    assert toxicity.op2_toxicity(odd.limit(0), one).count() == 0


# neighbours


def test_neighbours_recall_and_ties(spark):
    got = QUERIES["op3_neighbours"](spark, FULL).toPandas()
    table = pd.read_parquet(f"{FULL}/embeddings.parquet")
    x, ids, hits, asked = np.array(table.embedding.tolist(), float), table.vec_id.to_numpy(), 0, 0
    for q in np.flatnonzero(ids % 100 == 0):
        d = np.sqrt(((x - x[q]) ** 2).sum(1))
        d[q] = np.inf
        own = got[got.query_id == ids[q]].sort_values("rank")
        hits += len(set(own.vec_id) & set(ids[np.lexsort((ids, d))[:10]]))
        asked += 10
        assert np.allclose(own.score, d[[list(ids).index(v) for v in own.vec_id]], rtol=1e-12)
    assert hits / asked >= 0.9


def test_neighbours_on_odd_vectors(spark):
    rows = [(0, [1.0, 0.0]), (1, [1.0, 0.0]), (2, [0.0, 1.0]), (3, None), (4, [0.0, 0.0]), (5, [float("nan"), 1.0]), (6, [None, 1.0]), (7, [float("inf"), 1.0]), (8, [1.0]), (100, [1.0, 0.5]), (None, [1.0, 1.0]), (2, [0.0, 1.0])]
    df = spark.createDataFrame(rows, "vec_id bigint, embedding array<float>").withColumn("label", F.lit(1)).withColumn("code", F.lit("x"))
    got = [(r["query_id"], r["rank"], r["vec_id"]) for r in neighbours.op3_neighbours(df).orderBy("query_id", "rank").collect()]
    assert got == [(0, 1, 1), (0, 2, 100), (0, 3, 2), (100, 1, 0), (100, 2, 1), (100, 3, 2)]
    assert neighbours.op3_neighbours(df.limit(0)).count() == 0


def test_many_equal_vectors(spark):
    df = spark.range(300).select(F.col("id").alias("vec_id"), F.array(F.lit(1.0), F.when(F.col("id") < 250, 2.0).otherwise(F.col("id").cast("double"))).alias("embedding"))
    got = neighbours.op3_neighbours(df).filter("query_id = 100").orderBy("rank").collect()
    assert [r["vec_id"] for r in got] == list(range(10)) and {r["score"] for r in got} == {0.0}


# line dedup


def test_line_dedup_by_brute_force(spark):
    rng = np.random.default_rng(5)
    base = ["".join(rng.choice(list("abcdefgh "), n)).strip() for n in (24, 31, 32, 33, 40, 63, 64, 65, 90)]
    docs = []
    for k in range(60):
        lines = []
        for _ in range(4):
            s = list(base[rng.integers(len(base))])
            for _ in range(rng.integers(0, 3)):
                at, kind = rng.integers(len(s)), rng.integers(3)
                s[at : at + (kind != 0)] = [] if kind == 2 else [str(rng.choice(list("xyz")))]
            lines.append("".join(s))
        docs.append((k, "\n".join([*lines, "", " short "])))
    df = spark.createDataFrame(docs, "doc_id bigint, text string")

    def close(a, b):
        if a == b:
            return True
        if min(len(a), len(b)) < linededup.MIN_CHARS or abs(len(a) - len(b)) > 1:
            return False
        row = list(range(len(b) + 1))
        for i, x in enumerate(a, 1):
            row, last = [i], row
            for j, y in enumerate(b, 1):
                row.append(min(last[j] + 1, row[-1] + 1, last[j - 1] + (x != y)))
        return row[-1] <= 1

    seen, want = [], {}
    for k, text in docs:
        kept = []
        for line in text.split("\n"):
            key = line.strip(" \t\n\x0b\x0c\r")
            if not key or not any(close(key, s) for s in seen):
                kept.append(line)
            if key:
                seen.append(key)
        want[k] = "\n".join(kept)
    assert dict(texts_of(linededup.dedup_lines(df))) == want


def test_line_dedup_odd(odd):
    got = linededup.dedup_lines(odd)
    assert got.columns == odd.columns and got.count() == len(ODD)
    by = collections.defaultdict(list)
    for r in got.collect():
        by[r["doc_id"]].append(r["text"])
    assert by[1] == [None] and by[5] == [""] and by[10] == ["Line number one is here now"][:0] + [""] and by[9][0] == "line number one is here now\nline number one is here too"


# BPE and packing


def test_bpe_equals_the_library(documents):
    from tokenizers import Tokenizer

    lib = Tokenizer.from_file(bpe.default_path())
    texts = [t for _, t in texts_of(documents)] + [t or "" for *_, in [()] for t in []] + [r[1] or "" for r in ODD] + ["x" * 5000, " " * 3000 + "a", "'ll I've don't", "  \x85 \x1c½ ²³ Ⅷ", "ab" * 3000]
    codec = bpe.Codec(bpe.default_path())
    for mine, theirs, text in zip(codec.encode(texts), lib.encode_batch(texts, add_special_tokens=False), texts, strict=True):
        assert mine.tolist() == theirs.ids
        assert codec.decode(mine).decode() == lib.decode(theirs.ids, skip_special_tokens=False) == text


def test_bpe_query_digests(odd):
    codec = bpe.Codec(bpe.default_path())
    for r in bpe.op5_bpe(odd).collect():
        text = next(t for i, t, *_ in ODD if i == r["doc_id"]) or ""
        ids = next(codec.encode([text]))
        assert r["n_tokens"] == len(ids) and r["ids_sha256"] == hashlib.sha256(ids.astype("<u4").tobytes()).hexdigest() and r["decoded_sha256"] == hashlib.sha256(text.encode()).hexdigest()
    back = bpe.decode(bpe.encode(odd, bpe.default_path()), bpe.default_path())
    assert {r["text"] for r in back.collect()} == {t or "" for _, t, *_ in ODD}


def test_packing(odd, documents):
    from tokenizers import Tokenizer

    lib = Tokenizer.from_file(bpe.default_path())
    for df, most in ((odd, 1.5), (documents, 1.02)):
        got = packing.pack(df).toPandas()
        sizes = got.groupby("sequence_id").length.sum()
        assert sizes.max() <= 1024 and len(sizes) <= most * -(-got.length.sum() // 1024)
        ordered = got.sort_values(["sequence_id", "offset"])
        assert ((ordered.groupby("sequence_id").length.cumsum() - ordered.length) == ordered.offset).all()
        want = collections.Counter()
        for i, t in texts_of(df):
            ids = np.array([*lib.encode(t or "", add_special_tokens=False).ids, 2], "<u4")
            want.update((float("nan") if i is None else i, k, at, n, zlib.crc32(ids[at : at + n].tobytes())) for k, (at, n) in enumerate(packing.cuts(len(ids))) if i is not None)
        mine = collections.Counter((int(r.doc_id), r.piece, r.start, r.length, r.ids_crc32) for r in got.itertuples() if r.doc_id == r.doc_id)
        assert mine == want
    assert packing.pack(odd.limit(0)).count() == 0


def test_plan_holds_each_piece_once():
    rng = np.random.default_rng(2)
    for histogram in (np.bincount(rng.integers(1, 1025, 3000), minlength=1025), np.bincount([600] * 50, minlength=1025), np.bincount([100] * 1001, minlength=1025), np.zeros(1025, int)):
        total = np.zeros(1025, int)
        for config, many in packing.plan(histogram):
            assert sum(n * k for n, k in config.items()) <= 1024 and many > 0
            for n, k in config.items():
                total[n] += k * many
        assert (total == histogram).all()


# SimHash


def test_fingerprints_and_components(spark, documents, odd):
    def slow(text):
        w = [x for x in "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in text or "").translate({9: 32, 10: 32, 11: 32, 12: 32, 13: 32}).split(" ") if x]
        h = [xxhash.xxh64(" ".join(w[i : i + 3]).encode(), seed=42).intdigest() for i in range(max(1, len(w) - 2))] if w else []
        return sum(1 << k for k in range(64) if 2 * sum(x >> k & 1 for x in h) > len(h))

    for df in (documents.limit(300), odd):
        want = {i: slow(t) for i, t in texts_of(df)}
        assert {r["doc_id"]: int(r["fingerprint"], 16) for r in simhash.op6_simhash(df).collect()} == want
    kept = simhash.keep_one(odd)
    assert kept.columns == odd.columns and {r["doc_id"] for r in kept.collect()} >= {None, 1, 4, 6} and 5 not in {r["doc_id"] for r in kept.collect()}


def test_trie_links_by_brute_force(spark):
    rng = np.random.default_rng(7)
    base = rng.integers(0, 1 << 63, 12, dtype=np.uint64)
    v = np.unique(np.concatenate([base, *(base ^ np.uint64(0) ^ (np.uint64(1) << rng.integers(0, 64, 12).astype(np.uint64)) ^ (np.uint64(1) << rng.integers(0, 64, 12).astype(np.uint64)) for _ in range(120))]))
    parent = list(range(len(v)))

    def find(x):
        while parent[x] != x:
            x = parent[x]
        return x

    for i in range(len(v)):
        for j in np.flatnonzero(np.bitwise_count(v[i + 1 :] ^ v[i]) <= 2) + i + 1:
            a, b = find(i), find(int(j))
            parent[max(a, b)] = min(a, b)
    signed = v.view(np.int64)
    df = spark.createDataFrame([(int(x),) for x in signed], "fp bigint")
    star = {r["node"]: r["root"] for r in components.components(simhash.links(df), Scratch(spark, "test")).collect()}
    groups = collections.defaultdict(set)
    for k, x in enumerate(signed.tolist()):
        groups[find(k)].add(star.get(x, x))
    assert all(len(g) == 1 for g in groups.values()) and len({next(iter(g)) for g in groups.values()}) == len(groups)


def test_components_of_a_path(spark):
    edges = spark.range(200).select(F.col("id").alias("a"), (F.col("id") + 1).alias("b"))
    got = components.components(edges, Scratch(spark, "test")).collect()
    assert len(got) == 201 and {r["root"] for r in got} == {0}
    assert components.components(edges.limit(0), Scratch(spark, "test")).count() == 0


# substrings


def test_windows_and_words():
    data = "ab  c\tde\nab c de".encode()
    _, _, h = wordhash.words(data)
    assert len(h) == 6 and h[0] == h[3] and h[1] == h[4] and len(set(h.tolist())) == 3
    w = wordhash.windows(h, 3)
    assert w[0] == w[3] and len(set(w.tolist())) == 3
    x = np.array([5, 3, 3, 9, 1, 7], np.uint64)
    assert wordhash.lowest(x, 3).tolist() == [1, 1, 4, 4]


def brute_cut(rows, window=35):
    words = [(i, (t or "").encode().split()) for i, t in rows]
    n = collections.Counter(tuple(w[k : k + window]) for _, w in words for k in range(len(w) - window + 1))
    out = []
    for i, w in words:
        gone = {k + j for k in range(len(w) - window + 1) if n[tuple(w[k : k + window])] > 1 for j in range(window)}
        out.append((i, len(w), len(gone), hashlib.sha256(b" ".join(x for k, x in enumerate(w) if k not in gone)).hexdigest()))
    return collections.Counter(out)


def test_substring_dedup_by_brute_force(spark, odd):
    rng = np.random.default_rng(11)
    vocabulary = [f"v{k}" for k in range(5)]
    passage = [str(x) for x in rng.choice(vocabulary, 400)]
    docs = []
    for k in range(80):
        w = [str(x) for x in rng.choice(vocabulary, rng.integers(0, 60))]
        for _ in range(rng.integers(0, 3)):
            at = rng.integers(0, 340)
            w += passage[at : at + rng.integers(30, 60)] + [f"u{k}"]
        docs.append((k, " ".join(w)))
    docs += [(90, "same " * 100), (91, "same " * 36), (92, "same " * 35)]
    df = spark.createDataFrame(docs, "doc_id bigint, text string")
    tell = lambda rows: collections.Counter((r["doc_id"], r["n_words"], r["n_removed"], r["kept_sha256"]) for r in rows)
    assert tell(substring.op9_substring_dedup(df).collect()) == brute_cut(docs)
    assert tell(substring.op9_substring_dedup(odd).collect()) == brute_cut(texts_of(odd))
    cut = substring.cut(odd)
    assert cut.columns == odd.columns and {r["doc_id"]: r["text"] for r in cut.collect()}[7] == "a b tail"


# html and licences


def test_html_pages(spark):
    page = (
        '<html><head><title>T</title><style>p{}</style><script>var t="</p>";</script></head><body><header>Site</header><nav><ul><li><a href="/">Home</a></li></ul></nav><div class="ad">Buy this now.</div>'
        "<article><h1>Title &amp; more</h1><p><b>First   line<br>goes on<p>Short.</p><aside>By the way</aside><!-- x --><p>Last &lt;one&gt;</p></article><div id=comments><p>Nice text, I liked to read all of it very much.</p></div><form>Mail <input></form><footer>&copy; me</footer>"
    )
    assert html.extract(page) == "Title & more\nFirst line goes on\nShort.\nLast <one>"
    rows = [(1, "u", page), (2, None, None), (3, "u", ""), (4, "u", "<p"), (5, "u", "<script>never closed"), (5, "u", "<script>never closed"), (6, "u", "<p>" + "word " * 50_000)]
    df = spark.createDataFrame(rows, "page_id bigint, url string, html string").withColumn("text", F.lit(1)).withColumn("n_chars", F.lit("x"))
    got = html.op10_html(df).collect()
    assert len(got) == 7 and [r["n_chars"] for r in got if r["page_id"] == 6] == [249_999] and all(r["text"] == "" for r in got if r["page_id"] in (2, 3, 4, 5))
    assert html.op10_html(df.limit(0)).count() == 0


def test_html_of_the_given_pages():
    import re
    from html import unescape

    for page in pd.read_parquet(f"{FULL}/pages.parquet").html:
        body = page[page.index("<article>") + 9 : page.index("</article>")]
        blocks = [" ".join(unescape(re.sub("</?b>", "", x).replace("<br>", " ")).split()) for x in re.split(r"</?(?:p|h1)>", body)]
        assert html.extract(page) == "\n".join(b for b in blocks if b)


def test_licences():
    s = licenses.Scanner()
    assert s.scan(None) == (None, 0.0, 0) and s.scan("word") == (None, 0.0, 0)
    assert s.scan("hello\nReleased under the  MIT license\nbye")[:2] == ("MIT", 1.0)
    assert s.scan(licenses.TEMPLATES[6][1].replace("Software", "Program"))[0] == "MIT"
    assert s.scan("The license of this work is not known to anyone here.")[0] is None
