import hashlib
import json
import os
import random
import re
import zlib
from collections import Counter

import numpy as np
import pyarrow as pa
import pytest
import xxhash
from pyspark.sql import functions as F

import corpus_pipeline
from rootfinal.llm import boundaries, components, html_text, mixing, near_copies, personal_data, quality, sharding, token_count, vector_links
from rootfinal.llm import bpe_codec
from rootfinal.llm.queries import tokenizer_path
from rootfinal.llm.vocabulary import library_tokenizer

WORD, BYTE = "word_bpe_49k.json", "byte_bpe_50k.json"
ODD = ["", None, " ", "a", "Hello  world\n\n", "don't <|endoftext|> x", "x" * 5000, "　  é é ǅ", " lead\ttab ", "12 345!? ...", "tail   ", "\n \n a  b", "日本語 text", "a\x1c b", "<|endoftext|><|endoftext|>", "nul \0 a\0b \0\0"]


@pytest.fixture(scope="module")
def docs(spark):
    rows = [(i, t, ["a", None, "b"][i % 3], "extra") for i, t in enumerate(ODD)] + [(0, "", "a", "again")]
    return spark.createDataFrame(rows, "doc_id long, text string, source string, shard string")


def test_codec_equals_library(docs):
    lib = library_tokenizer(tokenizer_path(WORD))
    for r in bpe_codec.encode_column(docs.select("*"), tokenizer_path(WORD), ["doc_id"]).collect():
        ids = lib.encode(ODD[r.doc_id] or "", add_special_tokens=False).ids
        assert r.n_tokens == len(ids)
        assert r.ids_sha256 == hashlib.sha256(" ".join(map(str, ids)).encode()).hexdigest()
        assert r.decoded_sha256 == hashlib.sha256(lib.decode(ids, skip_special_tokens=False).encode()).hexdigest()


def test_ids_are_stored_and_decoded(spark, docs, tmp_path):
    lib = library_tokenizer(tokenizer_path(WORD))
    bpe_codec.encode_ids(docs, tokenizer_path(WORD), ["doc_id"]).write.parquet(str(tmp_path / "ids"))
    rows = bpe_codec.decode_ids(spark.read.parquet(str(tmp_path / "ids")), tokenizer_path(WORD)).collect()
    assert len(rows) == len(ODD) + 1
    for r in rows:
        ids = lib.encode(ODD[r.doc_id] or "", add_special_tokens=False).ids
        assert (list(r.ids), r.n_tokens) == (ids, len(ids))
        assert r.decoded == lib.decode(ids, skip_special_tokens=False)


def test_pipeline_ends_in_ids(spark, docs):
    assert dict(corpus_pipeline.encode(spark, docs, "").dtypes)["ids"] == "array<int>"


def tokens_of(text):
    return len(library_tokenizer(tokenizer_path(BYTE)).encode(text or "", add_special_tokens=False).ids)


def test_counts_equal_library():
    machine = token_count.TokenCounter(tokenizer_path(BYTE))
    for t in ODD:
        assert machine.count(t or "") == tokens_of(t), repr(t)


@pytest.mark.parametrize("chunk,limit", [(1, 1 << 19), (3, 1 << 19), (16, 200), (512, 1 << 19)])
def test_chunk_maps_compose_anywhere(chunk, limit):
    machine = token_count.TokenCounter(tokenizer_path(BYTE), limit, chunk)
    rng = random.Random(3)
    letters = ["a", "é", " ", "  ", "\n", "1", "!", "'s", "'", "ll", "　", "the", "\U0001f600", "٣"]
    texts = ["".join(rng.choice(letters) for _ in range(rng.randint(0, 60))) for _ in range(400)] + ["'" * 40, "x" * 700, "don't'stuff's"]
    assert machine.counts(pa.array(texts)).tolist() == [tokens_of(t) for t in texts]


def test_counts_of_long_texts_repeated_rows_and_no_rows(spark):
    long = "word and more words, 12 " * 4000 + "y" * 70_000
    rows = [(1, long, 5), (1, long, 6), (2, None, 7), (3, "", 8)]
    df = spark.createDataFrame(rows, "doc_id long, text string, n_tokens long")
    got = sorted((r.doc_id, r.n_bytes, r.n_tokens, r.over_limit) for r in token_count.count_tokens(df, tokenizer_path(BYTE), ["doc_id"]).collect())
    assert got == [(1, len(long), tokens_of(long), True)] * 2 + [(2, 0, 0, False), (3, 0, 0, False)]
    assert token_count.count_tokens(df.limit(0), tokenizer_path(BYTE), ["doc_id"]).count() == 0


def test_elias_fano_round_trip():
    rng = np.random.default_rng(4)
    for n in (0, 1, 2, 500):
        values = np.cumsum(rng.integers(0, 3000, n))
        ef = boundaries.EliasFano.of(values)
        assert ef.select_many(np.arange(n)).tolist() == values.tolist() == [ef.select(k) for k in range(n)]
    wide = np.cumsum(rng.integers(1 << 58, 1 << 59, 9))
    ef = boundaries.EliasFano.of(wide)
    assert ef.select_many(np.arange(9)).tolist() == wide.tolist() == [ef.select(k) for k in range(9)]


def test_blocks(spark, docs):
    lib = library_tokenizer(tokenizer_path(WORD))
    blocks = boundaries.write_blocks(spark, docs, tokenizer_path(WORD), 2, block_ids=8)
    rows = boundaries.read_blocks(blocks).orderBy("start").collect()
    assert [r.doc_id for r in rows] == sorted([*range(len(ODD)), 0])
    at = 0
    for r in rows:
        ids = [*lib.encode(ODD[r.doc_id] or "", add_special_tokens=False).ids, 2]
        assert (r.start, r.n_tokens, r.ids_crc32) == (at, len(ids), zlib.crc32(np.array(ids, "<u4").tobytes()))
        at += r.n_tokens
    got = {r.doc_id: list(r.ids) for r in boundaries.fetch(blocks, [4, 12]).collect()}
    assert got == {i: [*lib.encode(ODD[i], add_special_tokens=False).ids, 2] for i in (4, 12)}
    assert boundaries.read_blocks(boundaries.write_blocks(spark, docs.limit(0), tokenizer_path(WORD), 2)).count() == 0


class Watched:
    """The library's tokenizer, with the words that it was given to encode."""

    def __init__(self, tokenizer):
        self.tokenizer, self.words = tokenizer, []

    def __getattr__(self, name):
        return getattr(self.tokenizer, name)

    def encode_batch_fast(self, texts, **kw):
        self.words += " ".join(texts).split()
        return self.tokenizer.encode_batch_fast(texts, **kw)


def test_blocks_give_the_library_each_part_of_a_word_once(monkeypatch):
    watched = Watched(library_tokenizer(tokenizer_path(WORD)))
    monkeypatch.setattr(boundaries, "library_tokenizer", lambda path: watched)
    texts = pa.array(["Word, word. WORD", "WÖRD wörd!! (word)", "Word's"])
    for task in range(2):  # of one run
        flat, counts = boundaries._encoder(tokenizer_path(WORD), "some run")(texts)
        ids = [watched.encode(t, add_special_tokens=False).ids for t in texts.to_pylist()]
        assert (flat.tolist(), counts.tolist()) == (sum(ids, []), [len(i) for i in ids])
    assert sorted(w for w in watched.words if w != boundaries.MARK) == sorted(["word", ",", ".", "wörd", "!!", "(word)", "Word's"])
    boundaries._encoder(tokenizer_path(WORD), "another run")(texts)
    assert watched.words.count("word") == 2


@pytest.mark.parametrize("limit", [3, 600_000])
def test_blocks_encode_any_words_as_the_library_does(monkeypatch, limit):
    monkeypatch.setattr(boundaries, "STORE_WORDS", limit)
    lib, rng = library_tokenizer(tokenizer_path(WORD)), random.Random(11)
    letters = [*"abXYéÀßÿ×÷ªµ05'.,!*<>|_-\\ \t\n\x1c\x85\xa0\0", "İ", "Σ", "H\u0331", "h\u0331", "\u0301", "=\u0338", "你", "'s", "'LL", "<|endoftext|>", "<|ENDOFTEXT|>", "</w>", "The", "the."]
    texts = [t or "" for t in ODD] + ["".join(rng.choice(letters) for _ in range(rng.randint(0, 25))) for _ in range(1500)] + [f"ab{chr(c)} {chr(c)}AB {chr(c)}" for c in range(0x21, 0x400)]
    encode = boundaries._encoder(tokenizer_path(WORD), f"limit {limit}")
    for part in (texts[:700], [], [""], texts[700:]):
        flat, counts = encode(pa.array(part, pa.string()))
        ids = [lib.encode(t, add_special_tokens=False).ids for t in part]
        assert (flat.tolist(), counts.tolist()) == (sum(ids, []), [len(i) for i in ids])


def test_only_a_known_splitter_takes_words_apart(tmp_path):
    spec = json.load(open(tokenizer_path(WORD)))
    spec["normalizer"]["normalizers"].pop()  # no lower case
    (tmp_path / "cased.json").write_text(json.dumps(spec))
    texts, path = pa.array(["Word word, WORD"]), str(tmp_path / "cased.json")
    ids = library_tokenizer(path).encode(texts[0].as_py(), add_special_tokens=False).ids
    assert boundaries._encoder(path, "cased")(texts)[0].tolist() == ids != boundaries._encoder(tokenizer_path(WORD), "lower")(texts)[0].tolist()


def test_spans():
    text = "mail a.b@c.de, card 4111 1111 1111 1111 ip 10.0.0.256 10.0.0.1 call +49 (30) 1234567 iban DE89 3704 0044 0532 0130 00."
    found = [(k, text[a:b]) for k, a, b, _ in personal_data.find_spans(text) if k != "phone"]
    assert found[:3] == [("email", "a.b@c.de"), ("card", "4111 1111 1111 1111"), ("ip", "10.0.0.1")]
    assert ("iban", "DE89 3704 0044 0532 0130 00") in found
    assert personal_data.find_spans("") == []
    assert "4111" not in personal_data.redact(text, personal_data.find_spans(text))
    assert list(personal_data._emails("a@b@c.d x@@y.z @q.r")) == [(2, 7)]


def test_iban_before_capitals():
    de, gb = "DE89 3704 0044 0532 0130 00", "GB82 WEST 1234 5698 7654 32"
    for text, want in [
        (f"{de} BIC COBADEFF", [de]), (f"{de.replace(' ', '')} I paid", [de.replace(" ", "")]), (f"pay {de} {gb} 12 NOW", [de, gb]),
        (f"AB12 {de} X", [de]), (f"{de}0", []), ("DE89 3704 0044 0532 0130 01 BIC", []),
    ]:
        spans = personal_data.find_spans(text)
        assert [text[a:b] for k, a, b, _ in spans if k == "iban"] == want, text
        assert not any(w in personal_data.redact(text, spans) for w in want)


def test_quality(docs):
    rows = quality.apply_policy(quality.ledger(docs, ["doc_id", "shard"]))
    assert rows.count() == len(ODD) + 1 and rows.where("kept").count() == 0
    assert quality.measure("a b c a b c\nx\nx\n \n")[:5] == (8, 8, 0, 1, 6)
    alone = {r.rule: r.n_failed for r in quality.ablations(rows).collect()}
    assert alone["few_words"] == len(ODD) + 1


def test_long_junk_is_rejected(spark):
    rng = random.Random(10)
    junk = lambda n, vocabulary: " ".join(f"word{rng.randrange(vocabulary)}" for _ in range(n))
    rows = [(n, junk(n, 500)) for n in (1999, 2000, 2001, 3000, 4100, 30000)] + [(3001, junk(3000, 40))]
    rows += [(n + 7, junk(n, 3000)) for n in (2000, 5000, 30000)]
    got = {r.doc_id: r.failed_bits for r in quality.ledger(spark.createDataFrame(rows, "doc_id long, text string"), ["doc_id"]).collect()}
    bit = 1 << list(quality.RULES).index("few_distinct")
    assert {i for i, bits in got.items() if bits & bit} == {1999, 2000, 2001, 3000, 4100, 30000, 3001}


def test_shards(spark):
    df = spark.range(300).select(F.col("id").alias("doc_id"), F.repeat(F.lit("x"), (F.col("id") % 50).cast("int")).alias("text"))
    df = df.unionByName(spark.createDataFrame([(900, "y" * 900), (901, None)], "doc_id long, text string"))
    rows = sharding.shard(spark, df, 400).collect()
    assert len(rows) == 302
    sums = {}
    for r in rows:
        sums[r.shard] = sums.get(r.shard, 0) + r.n_bytes
    for r in rows:
        assert r.shard_bytes == sums[r.shard] and (r.shard_bytes <= 400 or (r.oversized and r.n_bytes == 900))
    shards = sorted(sums)
    assert not any(b.startswith(a) and a != b for a in shards for b in shards)
    assert sharding.shard(spark, df.limit(0), 400).count() == 0


def test_shards_equal_a_directory_split_bit_by_bit(spark):
    df = spark.range(400).select((F.col("id") % 350).alias("doc_id"), F.repeat(F.lit("y"), (F.col("id") * 7 % 40).cast("int")).alias("text"), F.lit("x").alias("shard"))
    df = df.unionByName(spark.sql("SELECT 5000L AS doc_id, 'same text of some bytes' AS text, 'x' AS shard FROM range(30)"))
    hashed = [(r.doc_id, r.h % (1 << 64), len(r.text)) for r in df.select("doc_id", "text", F.xxhash64("doc_id", "text").alias("h")).collect()]
    want = []

    def split(rows, depth):
        total = sum(n for *_, n in rows)
        if total <= 300 or len({h for _, h, _ in rows}) == 1:
            bits = f"{rows[0][1]:064b}"[:depth]
            want.extend((i, n, bits, depth, total, total > 300) for i, _, n in rows)
            return
        for side in (0, 1):
            part = [r for r in rows if r[1] >> (63 - depth) & 1 == side]
            if part:
                split(part, depth + 1)

    split(hashed, 0)
    assert sorted(tuple(r) for r in sharding.shard(spark, df, 300).collect()) == sorted(want)


def naive_spans(text):
    """The base kinds by their own words, one plain pass each."""
    ascii_digits = lambda x: [c for c in x if c in "0123456789"]
    rules = [
        ("email", r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+", lambda x: True),
        ("ip", r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)", lambda x: all(int(p) <= 255 for p in x.split("."))),
        ("card", r"[0-9]([\x20-]?[0-9])+", lambda x: 12 <= len(ascii_digits(x)) <= 19 and personal_data.luhn("".join(ascii_digits(x)))),
        ("phone", r"\+[0-9][\x20().0-9-]+[0-9]", lambda x: 9 <= len(ascii_digits(x)) <= 15),
    ]
    found = [(m.start(), i, f"{kind}:{m.start()}:{m.end()}") for i, (kind, rx, ok) in enumerate(rules) for m in re.finditer(rx, text) if ok(m.group())]
    return [x for *_, x in sorted(found)]


def test_personal_data_equals_plain_patterns(spark):
    rng = random.Random(14)
    bits = ["a", "b.c", "@", "x.de", " ", "-", "+49", "0", "7", "4111 1111 1111 1111", "10.0.0.1", "256.1.1.1", "(30)", ".", "1234567", "é", "\n", "+1 (555) 123-4567"]
    texts = ["".join(rng.choice(bits) for _ in range(rng.randint(0, 30))) for _ in range(1500)]
    real = [r.text for r in spark.read.parquet("/root/testdata/sf0.001/documents.parquet").collect()]
    df = spark.createDataFrame([(i, t, 7) for i, t in enumerate([*texts, *real, None, None])], "doc_id long, text string, spans int")
    for r in personal_data.span_table(df, ["doc_id", "spans"]).collect():
        text = ([*texts, *real, None, None][r.doc_id]) or ""
        want = naive_spans(text)
        assert r.base_sha256 == hashlib.sha256(",".join(want).encode()).hexdigest(), text
        assert (r.n_email, r.n_ip, r.n_card, r.n_phone) == tuple(sum(w.startswith(k) for w in want) for k in personal_data.BASE)
        assert r.spans_in == 7 and len(r.scores) == len([x for x in r.spans.split(",") if x])
    near = personal_data.find_spans("call +49 30 1234567"), personal_data.find_spans("zzzz +49 30 1234567")
    assert near[0][0][3] > near[1][0][3]


def test_quality_equals_plain_counting(spark):
    rng = random.Random(15)
    texts = ["".join(rng.choice(["a ", "b ", "c# ", "\n", "D\t", " \u3000", "é "]) for _ in range(rng.randint(0, 120))) for _ in range(300)] + [None, "", " ", "w " * 70_000]
    df = spark.createDataFrame([(i, t, 1, 2) for i, t in enumerate(texts)], "doc_id long, text string, n_words int, kept int")
    for r in quality.ledger(df, df.columns).collect():
        t = texts[r.doc_id] or ""
        words = re.findall(r"[^\x20\x09-\x0D]+", t)
        windows = [tuple(words[i : i + 3]) for i in range(len(words) - 2)]
        often = Counter(windows)
        repeated = {j for i, w in enumerate(windows) if often[w] > 1 for j in range(i, i + 3)}
        lines, seen = 0, set()
        for line in t.split("\n"):
            if re.search(r"[^\x20\x09-\x0D]", line):
                lines += line in seen
                seen.add(line)
        assert (r.n_words, r.word_chars, r.n_symbols, r.n_dup_lines, r.n_repeat_words) == (len(words), sum(map(len, words)), len(re.findall(r"[#*$%&|<>]", t)) if words else 0, lines, len(repeated))
    assert quality.good(df).columns == df.columns and quality.good(df.limit(0)).count() == 0


def test_pipeline_stages(spark, tmp_path):
    docs = spark.read.parquet("/root/testdata/sf0.001/documents.parquet").withColumn("n_words", F.lit(1)).withColumn("position", F.lit(2))
    docs = docs.unionByName(docs.where("doc_id < 50")).unionByName(docs.where("doc_id = 3").withColumn("text", F.lit(None).cast("string")))
    at = docs
    for name, stage in corpus_pipeline.STAGES[:-1]:
        at = stage(spark, at, "")
        assert at.columns == docs.columns, name
        at.write.parquet(str(tmp_path / name))
        at = spark.read.parquet(str(tmp_path / name))
    kept = {r.doc_id: r for r in spark.read.parquet(str(tmp_path / "quality_rules")).collect()}
    judged = quality.apply_policy(quality.ledger(docs, ["doc_id"])).where("kept").select("doc_id").distinct().collect()
    assert set(kept) == {r.doc_id for r in judged}
    single = [r.doc_id for r in spark.read.parquet(str(tmp_path / "near_dedup")).collect()]
    assert len(single) == len(set(single)) and set(single) <= set(kept)
    red = spark.read.parquet(str(tmp_path / "redact_personal_data")).collect()
    assert all(not personal_data.find_spans(r.text) or "<" in r.text for r in red) and len(red) == len(single)
    folder = str(tmp_path / "run")
    first = corpus_pipeline.run(spark, "/root/testdata/sf0.001", folder).orderBy("doc_id").collect()
    stamp = os.path.getmtime(f"{folder}/1-near_dedup/_SUCCESS")
    assert corpus_pipeline.run(spark, "/root/testdata/sf0.001", folder).orderBy("doc_id").collect() == first
    assert os.path.getmtime(f"{folder}/1-near_dedup/_SUCCESS") == stamp


def test_page_text():
    html = "<body><nav><a href=x>Home</a></nav><div class=ad>Buy</div><div id=main><h1>T &amp; x</h1><p><b>Bold</b> some  long text here<p>More text of the page<script>var</script></div><footer>f</footer></body>"
    assert html_text.main_text(html) == "T & x Bold some long text here More text of the page"
    assert html_text.main_text("") == ""


def test_page_text_of_sections_and_wrappers():
    para = lambda k: f"<p>{'w%d ' % k * 100}</p>"
    sections = "<section><h2>One</h2>" + para(1) * 5 + "</section><section><h2>Two</h2>" + para(2) * 12 + "</section>"
    ads = "<nav><a href=x>Home</a></nav><div class=ad>Buy</div><div class='cookie-notice'><p>We use cookies</p></div><div class='related'><a href=y>Other story</a></div>"
    whole = [("T", 1), ("One", 1), ("w1", 500), ("Two", 1), ("w2", 1200)]
    pages = [
        f"<body>{ads}<article><h1>T</h1>{sections}</article></body>",
        f"<body>{ads}<div id=page><h1>T</h1><div>{sections}</div></div></body>",
        f"<body>{ads}<h1>T</h1><div>{sections}</div></body>",
        f"<body>{ads}<div class='page has-sidebar'><div class='content-header'><h1>T</h1></div>{sections}</div></body>",
        f"<body>{ads}<article><h1>T</h1><div class='widget text'>{sections}</div></article></body>",
        f"<body class=menu>{ads}<div class=related-layout><h1>T</h1>{sections}</div></body>",
    ]
    for page in pages:
        words = html_text.main_text(page).split()
        assert [(w, words.count(w)) for w, _ in whole] == whole, page[:200]
        assert not {"Buy", "Home", "cookies", "Other"} & set(words), page[:200]


def test_density_equals_its_definition():
    """Counts and densities of every node against sums over its whole subtree."""
    rng = random.Random(13)

    def made(depth):
        if depth == 0 or rng.random() < 0.2:
            return "x" * rng.randint(1, 30) + " "
        tag = rng.choice(["div", "p", "a", "section", "b", "span"])
        return f"<{tag}>" + "".join(made(depth - 1) for _ in range(rng.randint(1, 4))) + f"</{tag}>"

    for _ in range(40):
        tree = html_text._Tree()
        tree.feed("<body>" + "".join(made(4) for _ in range(4)) + "</body>")
        tree.close()
        order = html_text._score(tree.root)

        def below(n):
            return [c for c in n.children if not isinstance(c, str)]

        def chars(n, linked=False):
            linked = linked or n.tag == "a"
            own = sum(len("".join(c.split())) for c in n.children if isinstance(c, str))
            parts = [chars(c, linked) for c in below(n)]
            return own + sum(p[0] for p in parts), (own if linked else 0) + sum(p[1] for p in parts)

        for n in order:
            inside, todo = [], below(n)
            while todo:
                inside.append(todo[0])
                todo = todo[1:] + below(todo[0])
            # an inner link's characters are links of every node around it
            assert n.chars == chars(n)[0]
            assert n.links == (n.chars if n.tag == "a" else chars(n)[1])
            assert n.tags == sum(c.tag not in html_text.FORMAT for c in inside) and n.link_tags == sum(c.tag == "a" for c in inside)


def test_selection_and_density_decide(monkeypatch):
    body = "".join(f"<p>{'word%d ' % i * 60}</p>" for i in range(4))
    page = f"<body><nav><ul><li><a href=x>Home</a></li></ul></nav><div>Buy now</div><div class=x><h1>T</h1>{body}<p>short</p></div><footer>Imprint of the site</footer></body>"
    want = html_text.main_text(page)
    assert want.startswith("T word0") and want.endswith("short") and not {"Home", "Buy", "Imprint"} & set(want.split())
    monkeypatch.setattr(html_text, "_main", lambda root: [root])
    assert {"Home", "Buy", "Imprint"} <= set(html_text.main_text(page).split())


def test_wrapped_pages_and_inline_words():
    body = "".join(f"<p>{'word%d ' % i * 60}</p>" for i in range(3))
    inner = f"<h1>T</h1>{body}<p>liked <span class=share>12</span> times</p>"
    for page in (f"<body><form><div>{inner}</div></form></body>", f"<body><header><h1>T</h1></header><article>{inner[10:]}</article></body>", f"<body><nav><a href=x>N</a></nav><main>{inner}</main><aside><article><p>{'other ' * 40}</p></article></aside></body>"):
        got = html_text.main_text(page)
        assert got.endswith("liked 12 times") and "word0" in got and "other" not in got, page[:60]


def test_page_rows(spark):
    long = "<article><h1>T</h1>" + f"<p>{'a long text ' * 500}</p>" * 20 + "</article>"
    df = spark.createDataFrame([(1, "u", None, "x"), (1, "u", None, "x"), (2, "v", "", "y"), (3, "w", long, "z")], "page_id long, url string, html string, text string")
    got = sorted((r.page_id, r.text, r.n_chars) for r in html_text.extract(df, ["page_id", "url"]).collect())
    assert got[:3] == [(1, "", 0), (1, "", 0), (2, "", 0)] and got[3][1].startswith("T a long") and got[3][2] == len(got[3][1]) == 1 + 20 * 6000
    assert html_text.extract(df.limit(0), ["page_id", "url"]).count() == 0


def test_mixing(spark):
    rows = [(i, "w " * (i % 7), ["a", "b", None][min(i % 20, 2)]) for i in range(400)]
    df = spark.createDataFrame(rows, "doc_id long, text string, source string")
    out = mixing.assign(df).collect()
    by = {}
    for r in out:
        t = by.setdefault(r.source, [0, 0, r.target, r.source_size])
        t[0] += r.taken
        t[1] += r.size
        assert r.taken <= 3 * r.size
    for taken, size, target, source_size in by.values():
        assert size == source_size and abs(taken - target) <= 6 and target <= 3 * size + 1e-9
    assert abs(sum(t[2] for t in by.values()) - sum(t[1] for t in by.values())) < 1e-6
    assert mixing.mix(df).count() == sum(r.copies for r in out)
    assert mixing.assign(df.limit(0)).count() == 0


def test_every_copy_has_its_position(spark):
    # a tenth of the words, half of the demand: its copies must run through the whole of the run
    rows = [(i, "w " * 10, "b" if i < 10 else "a") for i in range(60)]
    df = spark.createDataFrame(rows, "doc_id long, text string, source string")
    got = mixing.schedule(df).where("copy > 0").collect()
    assert [r.position for r in got] == sorted(r.position for r in got)
    small = [r for r in got if r.source == "b"]
    assert max(r.copy for r in small) == 3
    for c in (1, 2, 3):
        own = [r.position for r in small if r.copy == c]
        assert (c - 1) / 3 - 0.15 < min(own) and max(own) < c / 3 + 0.15
    order = [r.source for r in mixing.mix(df).collect()]
    assert order == [r.source for r in got] and "a" in order[-10:] and "b" in order[:10]
    flat = mixing.schedule(df, slope=0.0).where("source = 'b' AND copy > 0").collect()
    assert abs(flat[0].position - 5 / 300) < 1e-9 and abs(flat[-1].position - 295 / 300) < 1e-9


def test_vectors(spark):
    rng = np.random.default_rng(5)
    base = rng.normal(size=(20, 16))
    vecs = [(base[i % 20] + rng.normal(size=16) * 0.05 * (i % 3)).tolist() for i in range(120)]
    vecs += [None, [0.0] * 16, [float("nan")] * 16, []]
    df = spark.createDataFrame(list(enumerate(vecs)), "vec_id long, embedding array<float>")
    v = np.array(vecs[:120], np.float32).astype(float)
    v /= np.linalg.norm(v, axis=1)[:, None]
    link = v @ v.T >= 0.9
    np.fill_diagonal(link, False)
    old, vector_links.CELL = vector_links.CELL, 4
    try:
        got = {r.vec_id: r for r in vector_links.link(spark, df).collect()}
    finally:
        vector_links.CELL = old
    assert sum(got[i].n_links for i in range(120)) >= 0.98 * link.sum()
    assert all(got[i].n_links <= link[i].sum() for i in range(120))
    assert all(got[i].n_links == 0 and got[i].kept for i in range(120, 124))


def planted_pairs(rng, n, size, low, high):
    """2n vectors: pair i is rows i and n + i, of a cosine between low and high."""
    unit = lambda x: x / np.linalg.norm(x, axis=1, keepdims=True)
    a = unit(rng.normal(size=(n, size)))
    side = rng.normal(size=(n, size))
    side = unit(side - (side * a).sum(axis=1, keepdims=True) * a)
    c = rng.uniform(low, high, (n, 1))
    return np.concatenate([a, c * a + np.sqrt(1 - c * c) * side])


def test_vector_links_near_the_threshold(spark):
    x = planted_pairs(np.random.default_rng(8), 400, 64, 0.9005, 0.93)
    df = spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(x)], "vec_id long, embedding array<double>")
    got = {r.vec_id: r for r in vector_links.link(spark, df).collect()}
    assert sum(got[i].n_links for i in range(800)) >= 0.985 * 800
    assert sum(got[400 + i].component_id == i for i in range(400)) >= 0.985 * 400


def test_vector_links_of_mixed_lengths(spark, monkeypatch):
    rng = np.random.default_rng(9)
    pairs = [planted_pairs(rng, 400, size, 0.98, 0.99) for size in (8, 9)]
    df = spark.createDataFrame([(i, v.tolist()) for i, v in enumerate([*pairs[0], *pairs[1]])], "vec_id long, embedding array<double>")
    unit = [x / np.linalg.norm(x, axis=1, keepdims=True) for x in pairs]
    want = sum(int((u @ u.T >= 0.9).sum()) - len(u) for u in unit)
    assert sum(r.n_links for r in vector_links.link(spark, df).collect()) >= 0.99 * want
    # even where keys of different lengths clash
    at = np.ones(8), np.ones(9)
    rows = pa.table({"vec_id": list(range(4)), "vec": [at[i % 2].tobytes() for i in range(4)], "width": pa.array([8] * 4, pa.int32()), **{c: pa.array([0] * 4) for c in ("t", "k", "mine", "bi", "bj")}})
    monkeypatch.setattr(vector_links, "_keys", lambda unit: np.zeros((len(unit), 1), np.int64))
    got = pa.Table.from_batches(list(vector_links._cells(0.9)(iter(rows.to_batches())))).to_pylist()
    assert {(r["vec_id"], r["n"], r["root"]) for r in got} == {(0, 1, 0), (2, 1, 0), (1, 1, 1), (3, 1, 1)}


def test_near_copies(spark):
    rng = random.Random(6)
    words = [f"w{i}" for i in range(500)]
    text = [rng.choice(words) for _ in range(300)]
    near = text.copy()
    near[150] = "zzz"
    far = [rng.choice(words) for _ in range(300)]
    rows = [(5, " ".join(text)), (3, "  ".join(text)), (7, " ".join(near)), (1, " ".join(far)), (8, None), (9, ""), (10, "a b"), (11, "a b"), (12, "a c"), (5, " ".join(text))]
    df = spark.createDataFrame(rows, "doc_id long, text string")
    got = {r.doc_id: r.class_id for r in near_copies.classes(spark, df).collect()}
    assert got == {5: 3, 3: 3, 7: 3, 1: 1, 8: 8, 9: 9, 10: 10, 11: 10, 12: 12}
    assert near_copies.classes(spark, df.limit(0)).count() == 0


def test_near_copies_equal_all_pairs(spark, monkeypatch):
    """Classes against every pair of texts, with links only across groups, shared passages and small cells."""
    monkeypatch.setattr(near_copies, "CELL", 4)
    rng = random.Random(12)
    words = [f"w{i}" for i in range(400)]
    draw = lambda n: [rng.choice(words) for _ in range(n)]
    passage = draw(80)
    texts = []
    for _ in range(6):
        at = draw(rng.randint(60, 200))
        for _ in range(12):
            # each copy changes a little more, so that the ends of a chain do not link
            at = at.copy()
            for _ in range(2):
                at[rng.randrange(len(at))] = rng.choice(words)
            texts.append(at)
    texts += [draw(20) + passage for _ in range(15)] + [draw(4) for _ in range(5)] + [["a", "b"], ["a", "b"], []]
    df = spark.createDataFrame([(i, "  ".join(t)) for i, t in enumerate(texts)], "doc_id long, text string")
    hashed = [np.array([xxhash.xxh3_64_intdigest(w.encode()) & 0xFFFFFFFF for w in t], np.uint64) for t in texts]
    root = list(range(len(texts)))
    for i in range(len(texts)):
        for j in range(i):
            if texts[i] and texts[j] and near_copies.similar(hashed[i], hashed[j]):
                a, b = root[i], root[j]
                root = [min(a, b) if r in (a, b) else r for r in root]
    got = {r.doc_id: r.class_id for r in near_copies.classes(spark, df).collect()}
    assert got == dict(enumerate(root))


def test_one_row_of_each_class_stays(spark):
    a, b, c = ("one two three four five six seven " + x for x in ("eight", "nine ten eleven", "zero"))
    rows = [(5, a, 1), (5, a, 1), (3, a, 2), (5, b, 3), (7, b, 4), (9, c, 5), (9, c, 6), (None, a, 7), (10, None, 8), (11, "", 9)]
    df = spark.createDataFrame(rows, "doc_id long, text string, n int")
    got = {(r.doc_id, r.class_id) for r in near_copies.classes(spark, df).collect()}
    assert got == {(5, 3), (3, 3), (7, 3), (9, 9), (None, None), (10, 10), (11, 11)}
    kept = near_copies.drop_copies(spark, df)
    assert kept.columns == df.columns
    assert sorted((r.doc_id or 0, r.n) for r in kept.collect()) == [(0, 7), (3, 2), (9, 5), (10, 8), (11, 9)]


def test_components_of_chains_hubs_and_rings(spark):
    edges = [(i, i + 1) for i in range(100, 160)] + [(200, i) for i in range(201, 260)] + [(399, i) for i in range(340, 399)] + [(7, 8), (8, 9), (9, 7), (7, 7), (8, 7)]
    df = spark.createDataFrame(edges, "a long, b long")
    want = {i: 100 for i in range(100, 161)} | {i: 200 for i in range(200, 260)} | {i: 340 for i in range(340, 400)} | {7: 7, 8: 7, 9: 7}
    assert {r.v: r.component for r in components.components(spark, df).collect()} == want
    assert components.components(spark, df.limit(0)).count() == 0


def test_banded_alignment():
    rng = np.random.default_rng(7)
    for _ in range(60):
        a, b = (rng.integers(0, 3, rng.integers(1, 12)).astype(np.uint64) for _ in range(2))
        d = list(range(len(b) + 1))
        for x in a.tolist():
            e = [d[0] + 1]
            for j, y in enumerate(b.tolist()):
                e.append(min(d[j] + (x != y), d[j + 1] + 1, e[-1] + 1))
            d = e
        assert [near_copies.edit_distance_within(a, b, k) for k in range(12)] == [d[-1] <= k for k in range(12)]


def test_words_split_together_give_the_library_s_ids():
    odd = ["a\u00a0b", "\u3000c", "\u180ed", "e\u180ef", "\u180e", "\x1c", "g\x1ch", "\x1d\x1e", "\x85i", "\u0301j", "E\u0301", "\u03a3\u03a3", "it's", "'s", "12.5", "\ufb01", "\U0001f600", "x" * 500, "\u0130", "<|endoftext|>", "A", "\u2028"]
    words = list(dict.fromkeys([*odd, *(f"{w}{k}" for k in range(900) for w in ("Word", "\u00dcber", "it's-", "\u4e2d", "\x1cz"))]))
    path = tokenizer_path(WORD)
    library, encode = library_tokenizer(path), bpe_codec.word_encoder(path)
    for order in (words, words[::-1], odd, ["<|endoftext|>"], ["q"], []):
        ids, counts = encode(order)
        expected = [library.encode(w, add_special_tokens=False).ids for w in order]
        assert counts.tolist() == [len(e) for e in expected]
        assert ids.tolist() == [i for e in expected for i in e]
