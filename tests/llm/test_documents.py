"""Language, quality, secrets, chats, archives and pieces: brute force, held-out accuracy, round trips and odd inputs."""

import base64
import hashlib
import math
import re
import time
import zlib
from collections import Counter

import numpy as np
import pytest
from pyspark.sql import functions as F

from hamcover.llm import chat, langid, pieces, quality, secrets, warc
from hamcover.llm.common import shared_dir

LONG = "word " * 60_000


def crc(i, n):
    return zlib.crc32(str(i).encode()) % n


# Language.


def test_language_accuracy_on_held_out(spark):
    d = "/root/testdata/sf0.01"
    langs = {r.doc_id: r.lang for r in spark.read.parquet(f"{d}/documents.parquet").select("doc_id", "lang").collect()}
    got = langid.op2_language_id(spark, d).collect()
    assert len(got) == len(langs) and all(r.held_out == (crc(r.doc_id, 3) == 1) and 0 <= r.score <= 1 for r in got)
    held = [r for r in got if r.held_out]
    assert np.mean([r.lang_pred == langs[r.doc_id] for r in held]) > 0.97


class DirectScorer:
    """The definition, word by word, from the same counts."""

    def __init__(self, counts):
        self.languages = sorted({lang for lang, _, _ in counts})
        self.tables = [{} for _ in range(6)]
        for lang, word, n in counts:
            for order in range(6):
                for g in self.grams(word.decode("utf-8", "replace"), order):
                    self.tables[order].setdefault(g, Counter())[lang] += n
        self.sums = [{lang: sum(c[lang] for c in t.values()) for lang in self.languages} for t in self.tables]

    @staticmethod
    def grams(word, order):
        """Order 0: the word itself."""
        if not order:
            return [word]
        marked = f"^{word}$" if order > 1 else word
        return [marked[i : i + order] for i in range(len(marked) - order + 1)]

    def log(self, order, gram, lang):
        return math.log((self.tables[order][gram][lang] + 0.5) / (self.sums[order][lang] + 0.5 * len(self.tables[order])))

    def word(self, word):
        for order in (0, 5, 4, 3, 2, 1):
            known = [g for g in self.grams(word, order) if g in self.tables[order]]
            if known:
                return [sum(self.log(order, g, lang) for g in known) / len(known) for lang in self.languages]
        return [0.0] * len(self.languages)

    def predict(self, text):
        text = text or ""
        words = re.findall("[a-z\x80-\U0010ffff]+", text.lower())
        if not words or not any(c.isalpha() for c in text):
            return "und", 0.0
        total = [sum(x) for x in zip(*map(self.word, words), strict=True)]
        best = max(total)
        return self.languages[total.index(best)], 1 / sum(math.exp(x - best) for x in total)


@pytest.mark.parametrize("size, sample, vocabulary", [("sf0.001", 5_000, 30_000), ("sf0.01", 20, 150)])
def test_language_of_every_document_as_a_direct_scorer(spark, size, sample, vocabulary):
    docs = spark.read.parquet(f"/root/testdata/{size}/documents.parquet").limit(400)
    counts = [tuple(r) for r in langid.word_counts(langid.learnable(docs), sample, vocabulary).collect()]
    direct = DirectScorer([(lang, bytes(word), n) for lang, word, n in counts])
    assert max(Counter(lang for lang, _, _ in counts).values()) <= vocabulary and len(direct.languages) == 4
    model = langid.fit(langid.learnable(docs), sample, vocabulary)
    for r in langid.identify(docs, model).select("text", "language").collect():
        lang, score = direct.predict(r.text)
        assert r.language.lang_pred == lang and r.language.score == pytest.approx(score, abs=1e-4)


def test_rare_languages_stay(spark):
    rows = [(i, f"common words of number {'abcdefgh'[i % 8]}{'klmnop'[i % 6]}", "aa") for i in range(3000)] + [(9000 + i, "selten gehört", "zz") for i in range(3)]
    docs = spark.createDataFrame(rows, "doc_id bigint, text string, lang string")
    counts = langid.word_counts(docs, sample_docs=50, vocabulary=5).collect()
    assert {r.lang for r in counts} == {"aa", "zz"} and Counter(r.lang for r in counts) == {"aa": 5, "zz": 2}
    assert {r.n for r in counts if r.lang == "zz"} == {3} and max(r.n for r in counts) < 120
    assert langid.fit(docs, 50, 5).predict(["seltener"])[0][0] == "zz"


def test_language_backs_off_to_shorter_grams():
    model = langid.Model([("de", b"strasse", 5), ("de", b"wasser", 5), ("fr", b"maison", 5), ("fr", b"oiseaux", 5)])
    told = dict(zip(("Strasse", "oiseau", "wassern"), [x for x, _ in model.predict(["Strasse", "oiseau", "wassern"])], strict=True))
    assert told == {"Strasse": "de", "oiseau": "fr", "wassern": "de"}
    assert model.predict([None, "", "123 456 !!", "\n\t", "— …"]) == [("und", 0.0)] * 5
    assert model.predict(["日本"])[0][0] in ("de", "fr") and langid.Model([]).predict(["abc"]) == [("und", 0.0)]
    assert model.predict([LONG])[0][1] <= 1


def test_language_odd_rows(spark, make_docs):
    docs = make_docs(["the house is red", None, "", "42", LONG, "the house is red"], ids=[1, 2, None, 4, 5, 1]).withColumn("language", F.lit(1)).withColumn("score", F.lit(2))
    got = langid.identify(docs, langid.fit(docs)).select("doc_id", "language.lang_pred").collect()
    assert [r.lang_pred for r in got] == ["en", "und", "und", "und", "en", "en"]
    assert langid.identify(docs.where("false"), langid.fit(docs.where("false"))).count() == 0
    kept = langid.identified(docs)
    assert kept.columns == docs.columns and sorted(r.doc_id for r in kept.collect()) == [1, 1, 5]


# Quality.


def test_quality_on_held_out(spark):
    d = "/root/testdata/sf0.1"
    labels = {r.doc_id: r.quality for r in spark.read.parquet(f"{d}/labels.parquet").collect()}
    got = quality.op6_quality_knn(spark, d).collect()
    assert all(r.held_out == (crc(r.doc_id, 5) == 0) and r.predicted == int(r.score >= 0.3) and 0 <= r.score <= 1 for r in got)
    held = [(r.score, labels[r.doc_id]) for r in got if r.held_out and r.doc_id in labels]
    good, bad = [s for s, y in held if y == 1], [s for s, y in held if y == 0]
    assert np.mean([a > b for a in good for b in bad]) > 0.95


def test_quality_votes_as_brute_force():
    rng = np.random.default_rng(0)
    texts = ["".join(rng.choice(list("abcdeXYZ 1!"), 60)) for _ in range(40)]
    labels = np.array([i % 2 for i in range(40)], np.float32)
    rows = np.array([quality.features(t) for t in texts])
    voter = quality.Voter(rows, labels)
    got = voter.scores(texts + [None, ""])
    for t, s in zip(texts, got, strict=False):
        v = (quality.features(t) * voter.weight) @ voter.project
        cos = voter.vectors @ (v / np.linalg.norm(v))
        near = np.argsort(-cos)[: quality.NEIGHBOURS]
        w = np.maximum(cos[near], 0).astype(float) ** quality.POWER
        assert s == pytest.approx(((w * labels[near]).sum() + 1e-3 * 0.5) / (w.sum() + 1e-3), abs=1e-3)
    assert got[-1] == got[-2] == 0.5


def test_quality_features_cover_whole_texts():
    text = "".join(chr(97 + i % 23) for i in range(3000))
    whole = quality.features(text)
    old, quality.CHUNK = quality.CHUNK, 100
    try:
        assert np.allclose(quality.features(text), whole)
    finally:
        quality.CHUNK = old


def test_quality_without_labels(spark, make_docs):
    docs = make_docs(["a b c", None, ""]).withColumn("quality", F.lit(1))
    none = docs.select("doc_id", "text", F.lit(None).cast("int").alias("label"))
    got = quality.score_quality(docs, quality.fit(none)).select("quality.score").collect()
    assert [r.score for r in got] == [0.5] * 3


def test_quality_hangs_on_no_partitions(spark, make_docs):
    """The same scores under 1 and 16 partitions; many labelled copies, of either label, tie."""
    rng = np.random.default_rng(2)
    texts = ["".join(rng.choice(list("abcdeXYZ 1!"), 60)) for _ in range(60)] + ["the very same text"] * 80 + [LONG, None, ""]
    docs = make_docs(texts, ids=[*range(len(texts) - 1), 0])
    labels = docs.select("doc_id", "text", (F.xxhash64("doc_id") % 2 == 0).cast("int").alias("label"))
    found = []
    for n in (1, 16):
        voter = quality.fit(labels.repartition(n))
        rows = quality.score_quality(docs.repartition(n).withColumn("label", F.lit("x")), voter).select("doc_id", "text", "quality").collect()
        found.append(sorted((r.doc_id, r.text or "", r.quality.score, r.quality.predicted) for r in rows))
    assert found[0] == found[1] and len(found[0]) == len(texts)
    assert len({s for _, t, s, _ in found[0] if t == "the very same text"}) == 1
    assert quality.score_quality(docs.where("false"), voter).count() == 0


# Secrets.


def brute_base(text):
    text = text or ""
    found = [("assign", m.start(), m.end()) for m in re.finditer(r"""(password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", text, re.I | re.A) if len(m[2]) >= 6]
    found += [("access", m.start(), m.end()) for m in re.finditer(r"AKIA[A-Z0-9]+", text) if len(m[0]) >= 20]
    found += [("hex", m.start(), m.end()) for m in re.finditer(r"[0-9a-f]+", text) if len(m[0]) >= 24]
    order = ("assign", "access", "hex")
    return sorted(found, key=lambda x: (x[1], order.index(x[0])))


SECRET = "wJalrXUtnFEMI/K7MDENG/bPxRfiCYEXAMPLEKEY"
TEXTS = [
    None,
    "",
    "nothing here",
    f"é token = '{'ab12' * 8}' TOKEN:short x",
    f"id AKIA{'ABCD' * 5}\nvalue {SECRET}\nhttps://api.example.com/v1",
    f"alone {SECRET}",
    "https://api.example.com/v1 alone",
    f"AKIA{'ABCD' * 5}\n\nnext\n\n{SECRET}",
    f"AKIA{'ABCD' * 5}{' x' * 600}{SECRET}",
    "api_key=abcdef apikey : 'ABCDEF' passwd=12345 Secret=longenough",
    f"user = bob {'0123456789abcdef' * 2} arn:aws:iam::123:role/x",
    "日本 token=日本 token=abcdef1",
    LONG + " password: hunter22",
]


def test_secret_spans(spark, make_docs):
    docs = make_docs(TEXTS).withColumn("secrets", F.lit(0)).withColumn("spans", F.lit(0))
    got = secrets.scan_secrets(docs).select("text", "secrets").collect()
    for r in got:
        base = [tuple(x) for x in r.secrets.base]
        assert base == brute_base(r.text)
        assert set(base) <= {tuple(x) for x in r.secrets.spans}
    kinds = [sorted({x.kind for x in r.secrets.spans}) for r in got]
    assert kinds[4] == ["access", "endpoint", "secret"] and kinds[5] == kinds[6] == [] and kinds[7] == kinds[8] == ["access"]
    assert "ident" in kinds[10] and "endpoint" in kinds[10] and "hex" in kinds[10]
    assert secrets.scan_secrets(docs.where("false")).count() == 0


def test_secrets_of_any_length(spark, make_docs):
    key, url, user = "aB3" * 170, "https://h.example/" + "p" * 900, "user=" + "n" * 300
    text = f"AKIA{'ABCD' * 5}\n\n{key}== {url} {user} end"
    docs = make_docs([text, text, "x" + key, "long " * 50_000 + text])
    for r in secrets.scan_secrets(docs).where("doc_id <> 2").select("text", "secrets.spans").collect():
        assert [(x.kind, r.text[x.start : x.end]) for x in r.spans][1:] == [("secret", key + "=="), ("endpoint", url), ("ident", user)]
    kept = {r.doc_id: r.text for r in secrets.redacted(docs).collect()}
    assert kept[0] == kept[1] == "<access>\n\n<secret> <endpoint> <ident> end" and kept[2] == "x" + key and kept[3].endswith(kept[0])


def test_secret_query_on_the_table(spark, sf):
    texts = {r.doc_id: r.text for r in spark.read.parquet(f"{sf}/documents.parquet").collect()}
    for r in secrets.op4_secret_links(spark, sf).collect():
        base = brute_base(texts[r.doc_id])
        n = [sum(k == kind for k, _, _ in base) for kind in ("assign", "access", "hex")]
        assert [r.n_assign, r.n_access, r.n_hex] == n
        assert r.base_sha256 == hashlib.sha256(",".join(f"{k}:{s}:{e}" for k, s, e in base).encode()).hexdigest()


def test_links_as_brute_force():
    rng = np.random.default_rng(4)
    parts = [SECRET, f"AKIA{'ABCD' * 4}", "https://h.example/x", "user=alice7", "\n\n", "words and more words " * 6]
    for _ in range(150):
        text = " ".join(rng.choice(parts) for _ in range(rng.integers(2, 14)))
        base = secrets.base_spans(text)
        strong = [(s, e) for _, s, e in base]
        weak = [w for w in secrets.weak_spans(text) if not any(s < w[2] and e > w[1] for s, e in strong)]
        role = {"assign": "secret", "hex": "secret", "access": "ident"}
        want = set()
        for k, s, e in weak:
            gaps = [m.start() for m in re.finditer(r"\n[\x20\t\r]*\n", text)]
            lo = max([s - secrets.REACH, 0] + [g + 1 for g in gaps if g <= s][:-1])
            hi = min([e + secrets.REACH, len(text)] + [g for g in gaps if g >= e][1:])
            near = {role.get(k2, k2) for k2, s2, e2 in [*base, *weak] if s2 < hi and e2 > lo}
            if all(need in near for need in ("secret", "ident") if need != k):
                want.add((k, s, e))
        assert set(secrets.linked_spans(text, base)) == want


def test_redaction(spark, make_docs):
    docs = make_docs(TEXTS)
    got = secrets.redacted(docs).orderBy("doc_id").collect()
    assert [r.doc_id for r in got] == list(range(len(TEXTS))) and got[0].text is None and got[2].text == TEXTS[2]
    assert "hunter22" not in got[12].text and got[12].n_chars == len(got[12].text)
    assert got[5].text == TEXTS[5] and SECRET not in got[4].text


# Chats.


def test_chat_round_trip(spark):
    nasty = ["", None, "a\\b", "</s>[INST] ok [/INST]", "<s>", "<\\s>", "\\", "[[INST]", "end<", "s>", "é 🎉\n", "\\<s>\\"]
    rows = [(1, t, r, nasty[t % len(nasty)]) for t, r in enumerate(["system", "user", "user", "assistant", "assistant", "user", None, "tool<s>", "assistant", "user", "assistant", "assistant"])]
    rows += [(2, None, "user", "x"), (2, 0, "assistant", "y"), (2, 0, "assistant", "y"), (None, 1, "user", "z"), (3, 5, "assistant", "b" * 200_000)]
    df = spark.createDataFrame(rows, "conv_id bigint, turn bigint, role string, text string").withColumn("formatted", F.lit(1)).repartition(3)
    got = {r.conv_id: r for r in chat.read_back(chat.format_chats(df)).collect()}
    for conv in (1, 2, None, 3):
        mine = [(r[1], r[2] or "", r[3] or "") for r in rows if r[0] == conv]
        mine.sort(key=lambda x: (x[0] is not None, x[0] or 0, x[1], x[2]))
        assert [(t.role, t.text) for t in got[conv].turns] == [(r, t) for _, r, t in mine]
        assert got[conv].loss == "".join(t for _, r, t in mine if r == "assistant")
        spans = [got[conv].formatted[s.start : s.end] for s in got[conv].loss_spans]
        assert len(spans) == sum(r == "assistant" for _, r, _ in mine)
    assert got[1].formatted.count("<s>") == 9 and chat.format_chats(df.where("false")).count() == 0


def test_long_conversations_take_no_square_of_time(spark):
    """50,000 turns, alternating in one conversation and by one role in the other."""
    turns = spark.range(50_000).select(F.col("id").alias("turn"), F.concat(F.lit("text <s> "), F.col("id").cast("string"), F.repeat(F.lit(" x"), 30)).alias("text"))
    both = turns.select(F.lit(1).cast("long").alias("conv_id"), "turn", F.when(F.col("turn") % 2 == 0, "user").otherwise("assistant").alias("role"), "text")
    both = both.union(turns.select(F.lit(2).cast("long").alias("conv_id"), "turn", F.lit("assistant").alias("role"), "text"))
    began = time.monotonic()
    found = chat.read_back(chat.format_chats(both)).select("conv_id", F.size("turns").alias("n"), F.sha2("loss", 256).alias("loss"), F.size("loss_spans").alias("spans")).collect()
    assert time.monotonic() - began < 60
    texts = [f"text <s> {i}{' x' * 30}" for i in range(50_000)]
    digest = lambda x: hashlib.sha256("".join(x).encode()).hexdigest()
    assert sorted(map(tuple, found)) == [(1, 50_000, digest(texts[1::2]), 25_000), (2, 50_000, digest(texts), 50_000)]


# Archives.


def page_rows(spark, rows):
    return spark.createDataFrame(rows, "page_id bigint, url string, html string")


def test_warc_round_trip(spark):
    rng = np.random.default_rng(0)
    rows = [(i, f"http://h/{i}\r\nx", "".join(map(chr, rng.integers(32, 0x3000, 800)))) for i in range(60)]
    rows += [(100, None, None), (101, "u", ""), (102, "u", "same"), (103, "u", "same"), (103, "u", "same"), (None, "n", "same"), (104, "u", "big" * 900_000), (None, "n", "alone")]
    pages = page_rows(spark, rows).withColumn("payload", F.lit(1)).withColumn("digest", F.lit(2)).repartition(3)
    manifest = warc.write_archives(warc.with_revisits(pages), shared_dir(spark, "test-warc"), archive_bytes=40_000)
    assert manifest.count() > 3
    for size in (500, 7_000, 1 << 24):
        got = warc.read_archives(manifest, range_bytes=size).collect()
        assert len(got) == len(rows)
        want = {}
        for i, _, html in rows:
            data = (html or "").encode()
            mates = [p for p, _, h in rows if (h or "") == (html or "") and p is not None]
            top = max(mates, default=None)
            want.setdefault(i, set()).add((len(data), base64.b32encode(hashlib.sha1(data).digest()).decode(), "response" if top is None or i == top else "revisit", None if top is None or i == top else top))
        assert all((r.payload_bytes, r.payload_digest, r.record_type, r.refers_to) in want[r.page_id] for r in got)
        assert all(r.digest_ok for r in got if r.record_type == "response")
        full = {r.page_id: r.payload for r in got if r.record_type == "response" and r.page_id is not None}
        assert full[5].decode() == rows[5][2] and full[101] == b""
        assert [r.target_uri for r in got if r.page_id == 3] == ["http://h/3%0D%0Ax"]


def test_warc_magic_inside_of_payloads_and_damage(spark, tmp_path):
    inner = warc._page_record("other", 7, "u", b"inner", "X", None)
    own = "0f0f0f0f-0000-4000-8000-000000000000"
    raw = zlib.compressobj(0, zlib.DEFLATED, 31)
    stored = raw.compress(b"WARC/1.1\r\nWARC-Type: response\r\nWARC-Record-ID: <urn:x-page:1>\r\nWARC-Warcinfo-ID: <urn:uuid:%s>\r\nContent-Length: %d\r\n\r\n" % (own.encode(), 4 + len(inner)) + b"\r\n\r\n" + inner + b"\r\n\r\n") + raw.flush()
    good = warc._page_record(own, 2, "u", b"second", base64.b32encode(hashlib.sha1(b"second").digest()).decode(), None)
    path = tmp_path / f"pages-{own}.warc.gz"
    path.write_bytes(stored + b"\x1f\x8b\x08junk" + good + good[:20])
    uri = f"file://{path}"
    for size in (1 << 20, 40, 7):
        ids = [r["page_id"] for start in range(0, path.stat().st_size, size) for r in warc.range_records(uri, start, start + size)]
        assert ids == [1, 2]


def test_warc_of_no_pages(spark):
    manifest = warc.write_archives(warc.with_revisits(page_rows(spark, [(1, "u", "x")]).where("false")), shared_dir(spark, "test-warc"))
    assert manifest.count() == 0 and warc.read_archives(manifest).count() == 0


# Pieces.

ODD = ["", " ", "a", " a", "a ", "a  b", "日本語 テスト 🎉🎉 \x01", "é́ ñ\n\n\t tab", "   ", "<s> </s> <unk>", "a\n b", " x", "🏳️‍🌈 zwj", "\x7f\x80", "x" * 3000]


def test_pieces_parity_and_round_trip(spark, sf, make_docs):
    model = pieces.read_model()
    docs = spark.read.parquet(f"{sf}/documents.parquet").unionByName(make_docs([*ODD, None, LONG]))
    got = pieces.encode_pieces(docs.withColumn("pieces", F.lit(1)), model, parity_every=1).select("text", "pieces").collect()
    assert all(r.pieces.parity and r.pieces.round_trip for r in got)
    back = pieces.decode_pieces(pieces.encode_pieces(make_docs([*ODD, None]), model).select("text", "pieces.ids"), model).collect()
    assert all(r.decoded.text == (r.text or "") for r in back)
    assert pieces.encode_pieces(docs.where("false"), model).count() == 0


def test_pieces_of_repeated_rows_and_clashing_names(spark, make_docs):
    docs = make_docs([*ODD, *ODD, None, None, LONG, LONG], ids=[7] * (2 * len(ODD) + 4)).withColumn("ids", F.lit("x")).withColumn("parity", F.lit(0))
    found = pieces.encode_pieces(docs, pieces.read_model()).select("doc_id", "text", "ids", "pieces").collect()
    assert len(found) == docs.count() and {r.doc_id for r in found} == {7} and {r.ids for r in found} == {"x"}
    by_text = {}
    for r in found:
        assert by_text.setdefault(r.text, r.pieces) == r.pieces and r.pieces.parity


def test_pieces_of_the_marker_character(spark, make_docs):
    got = pieces.encode_pieces(make_docs(["x▁y", "▁"]), pieces.read_model(), parity_every=1).select("pieces").collect()
    assert all(r.pieces.parity and not r.pieces.round_trip for r in got)


def test_unigram_models_are_rebuilt():
    from sentencepiece import SentencePieceProcessor, sentencepiece_model_pb2

    proto = sentencepiece_model_pb2.ModelProto()
    proto.ParseFromString(pieces.read_model())
    proto.trainer_spec.model_type = pieces.UNIGRAM
    for k, p in enumerate(proto.pieces):
        if p.type == pieces.NORMAL:
            p.score = -5.0 - len(p.piece) * 0.01 - (k % 97) * 0.013
    model = proto.SerializeToString()
    other, mine = SentencePieceProcessor(model_proto=model), pieces.Backend(model)
    texts = ["hello world", "the  cat sat", " on  mats", "naïve café ok"]
    assert [np.frombuffer(b, np.int32).tolist() for b in mine.encode(texts)] == other.encode(texts)


def test_pieces_parity_of_every_text(spark, sf, make_docs):
    import corpus_pipeline

    assert all(r.parity for r in pieces.op9_pieces(spark, sf).select("parity").collect())
    got = corpus_pipeline.tokens(spark, make_docs(["some words here", " a  b ", "日本 ﬁn\n\tx", "", None, "<s> </s>"]), sf)
    assert [r.parity for r in got.select("parity").collect()] == [True] * 6


def test_pieces_parity_by_word_as_by_text():
    from sentencepiece import SentencePieceProcessor

    model = pieces.read_model()
    backend, other = pieces.Backend(model), SentencePieceProcessor(model_proto=model)
    backend.compare()
    texts = ["one two", "two three", " three ", "x▁y one", "é\u0301 日本語 ﬁ", "four"]
    ids = other.encode(texts)
    assert backend.by_word and backend.parity(texts, backend.encode(texts)) == [True] * 6
    # A wrong backend is reported for every text with the word, and no other.
    real = backend.tokenizer

    class Wrong:
        def encode_batch_fast(self, words, **kw):
            return real.encode_batch_fast([w.replace("two", "too") for w in words], **kw)

    backend.known.clear()
    backend.tokenizer = Wrong()
    packed = backend.encode(texts)
    want = [list(pieces.np.frombuffer(x, "int32")) == y for x, y in zip(packed, ids, strict=True)]
    assert backend.parity(texts, packed) == want == [False, False, True, True, True, True]
