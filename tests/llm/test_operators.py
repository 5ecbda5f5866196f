"""The training-data operators against brute force, round trips and hard rows."""

import hashlib
import math
import random
import zlib
from collections import Counter

import numpy as np
import public_tokenizers
import pytest
import tiktoken

from patternjoin.llm import byte_bpe, html_extraction, lm_scoring, suffix_dedup, topk_search, warc_archive
from patternjoin.llm import webp_lossless as webp
from patternjoin.llm.language_id import fit_filter, identify
from patternjoin.llm.near_dedup import near_duplicates
from patternjoin.llm.source_mixing import capped_targets, min_cost_flow, mix_sources

RANKS = public_tokenizers.path("byte_bpe_50k.tiktoken")
SCHEMA = "doc_id long, text string, lang string, source string, n_chars long, fp string, comp string, d1 long, size long, row long"
LONG = "word " * 50_000


def table(spark, rows):
    return spark.createDataFrame([(i, t, l, s, None, "x", "y", 1, 2, 3) for i, t, l, s in rows], SCHEMA)


@pytest.fixture(scope="module")
def odd(spark):
    g = random.Random(5)
    text = lambda n: " ".join(g.choice("alpha beta gamma delta eps zeta eta theta iota kappa".split()) for _ in range(n))
    base = text(120)
    rows = [(0, None, None, None), (1, "", "en", "a"), (2, " \n\t", "en", "a"), (3, LONG, "en", "b"), (4, base, "en", "a"), (4, base, "en", "a"),
            (5, base, None, None), (6, base.replace("alpha", "omega", 1), "de", "b"), (7, "123 !?", "en", "c"), (None, base, "en", "a"), (8, "日本語 🙂", "de", "c")]
    rows += [(i, text(g.randint(1, 80)), g.choice(["en", "de"]), g.choice("abc")) for i in range(20, 60)]
    return table(spark, rows)


@pytest.fixture(scope="module")
def empty(spark):
    return spark.createDataFrame([], SCHEMA)


def shingles(text, w):
    words = (text or "").encode().lower().split()
    return {tuple(words[i:i + w]) for i in range(max(1, len(words) - w + 1))} if words else set()


def test_near_duplicates(spark, odd, empty):
    rows = [(r["doc_id"], r["text"]) for r in odd.collect()]
    for w in (2, 5):
        sets = [(i, shingles(t, w)) for i, t in rows]
        comp = {i: i for i, _ in sets if i is not None}
        for _ in range(len(sets)):
            for i, a in sets:
                for j, b in sets:
                    if i is not None and j is not None and a and 100 * len(a & b) >= 80 * len(a | b):
                        comp[i] = comp[j] = min(comp[i], comp[j])
        got = near_duplicates(odd, width=w).collect()
        assert len(got) == len(rows)
        for r in got:
            if r["doc_id"] is not None:
                assert r["component_id"] == comp[r["doc_id"]] and r["kept"] == (r["doc_id"] == comp[r["doc_id"]])
    assert near_duplicates(empty).count() == 0


def test_language(spark, odd, empty):
    model = fit_filter(odd)
    got = {r["doc_id"]: r for r in identify(odd, model).collect()}
    assert all(got[i]["lang_pred"] == "und" and got[i]["score"] == 0 for i in (0, 1, 2, 7))
    assert got[8]["lang_pred"] in ("en", "de") and all(0 <= r["score"] <= 1 for r in got.values())
    assert identify(empty, fit_filter(empty)).count() == 0


def test_bpe_equals_library(spark, odd, empty):
    ranks = byte_bpe.read_ranks(RANKS)
    library = tiktoken.Encoding("own", pat_str=public_tokenizers.PATTERN, mergeable_ranks=ranks, special_tokens={})
    for r, t in zip(byte_bpe.byte_bpe(odd, RANKS, public_tokenizers.PATTERN).collect(), odd.collect(), strict=True):
        assert list(r["token_ids"]) == library.encode_ordinary(t["text"] or "") and r["decoded_ok"]
    g = random.Random(2)
    own = byte_bpe.MergeReplay(ranks, public_tokenizers.PATTERN)
    texts = ["".join(g.choice("abcdeit hns.!0é🙂\n\x1c ") for _ in range(g.randint(0, 200))) for _ in range(300)]
    assert own.encode_all(texts) == [library.encode_ordinary(t) for t in texts]
    assert byte_bpe.byte_bpe(empty, RANKS, public_tokenizers.PATTERN).count() == 0


def test_top_k(spark):
    g = np.random.default_rng(1)
    rows = [(i, g.normal(size=8).round(2).tolist()) for i in range(220)] + [(300, None), (350, [1.0, None] * 4), (400, [math.inf] * 8), (None, [1.0] * 8), (401, [])]
    rows += [(500, rows[3][1]), (501, rows[3][1])]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<float>")
    ok = [(i, np.floor(256 * np.array(v, np.float32).astype(float)).astype(int)) for i, v in rows
          if i is not None and v and all(x is not None and math.isfinite(x) for x in v)]
    want = set()
    for q, a in ok:
        if q % 50 == 0:
            best = sorted((-int(a @ b), i) for i, b in ok if i != q)[:5]
            want |= {(q, n + 1, i, -s) for n, (s, i) in enumerate(best)}
    assert {tuple(r) for r in topk_search.exact_top_k(df, block_rows=32, query_rows=2).collect()} == want
    assert topk_search.exact_top_k(df.limit(0)).count() == 0


def test_archive(spark):
    big, bigger = "x" * 1000, "é" * 600
    rows = [(1, "u1", big), (2, None, big), (3, "u\r\n3", bigger), (4, "u", "small"), (5, "u", "small"), (6, "u", None), (7, "u", big), (7, "u", big), (None, "u", big)]
    archive = warc_archive.new_archive(spark)
    warc_archive.write_archive(spark.createDataFrame(rows, "page_id long, url string, html string"), archive)
    got = warc_archive.archive_report(spark, archive).collect()
    assert len(got) == len(rows)
    for r in got:
        if r["page_id"] is not None:
            body = (dict((i, h) for i, _, h in rows)[r["page_id"]] or "").encode()
            assert r["payload_digest"] == hashlib.sha1(body).hexdigest() and r["payload_bytes"] == len(body)
            assert (r["record_type"], r["refers_to"]) == (("revisit", 7) if r["page_id"] in (1, 2) else ("response", None))
    for r in warc_archive.reconstruct(spark, archive).collect():
        head, _, rest = bytes(r["warc"]).partition(b"\r\n\r\n")
        assert head.startswith(b"WARC/1.1\r\n") and rest.endswith(b"\r\n\r\n") and f"Content-Length: {len(rest) - 4}".encode() in head
    assert spark.read.parquet(archive.payloads).count() == 4


def test_language_model(spark, odd, empty):
    from pyspark.sql import functions as F

    held = F.crc32(F.coalesce(F.col("doc_id").cast("string"), F.lit("")).cast("binary")) % 5 == 1
    for frequent in (500_000, 3):
        got = lm_scoring.score_texts(odd, held, RANKS, frequent_words=frequent).collect()
        rows = [(r["doc_id"], (r["text"] or "").encode().lower().split() + [None]) for r in odd.collect()]
        c = Counter(w for i, ws in rows if zlib.crc32(("" if i is None else str(i)).encode()) % 5 != 1 for w in ws)
        n, v = sum(c.values()), len(c)
        want = {i: (len(ws), sum(c[w] > 0 for w in ws), sum(math.log10((c[w] + 0.5) / (n + 0.5 * (v + 1))) for w in ws)) for i, ws in rows}
        for r in got:
            assert (r["n_tokens"], r["n_known"], r["train_tokens"]) == (*want[r["doc_id"]][:2], n)
            assert r["base_score"] == pytest.approx(want[r["doc_id"]][2]) and r["score"] < 0
    assert lm_scoring.score_texts(empty, held, RANKS).count() == 0


def test_model_learns_from_every_text(spark):
    words = [w for w in (t.decode("ascii", "ignore") for t in byte_bpe.read_ranks(RANKS)) if w.isalpha()]
    single = [(w, ids[0]) for w, ids in zip(words, lm_scoring.subword_ids(words, RANKS), strict=True) if len(ids) == 1]
    rows = [(k, w) for k, (w, _) in enumerate(single)] * (1 + 2_400 // len(single))
    rows = [(k, *r[1:]) for k, r in enumerate(rows)] + [(len(rows) + k, "a" * (k % 7)) for k in range(2_400)]
    p, q = lm_scoring.initial(), lm_scoring.fit_model(spark.createDataFrame(rows, "doc_id long, text string"), RANKS)
    moved = (p["E"] != q["E"]).any(axis=1)
    assert len(rows) > 4_000 and all(moved[i] for _, i in single)


def test_vocabulary_is_merged_from_training_texts(spark):
    g = random.Random(6)
    syllables = ["tion", "qu", "zor", "mek", "la", "éa", "x"]
    texts = [" ".join("".join(g.choices(syllables, k=3)) for _ in range(60)) for _ in range(1_300)]
    v = lm_scoring.merged_vocabulary(texts[:200], RANKS)
    assert len(v) <= lm_scoring.END and len(set(v)) == len(v) and {bytes([b]) for b in range(256)} <= set(v)
    odd = ["", "日本\n\n", *texts[200:300]]
    before, after = lm_scoring.subword_ids(odd, RANKS), lm_scoring.subword_ids(odd, RANKS, v)
    assert [b"".join(v[i] for i in ids).decode() for ids in after] == odd
    assert sum(map(len, after)) < 0.6 * sum(map(len, before))
    assert lm_scoring.merged_vocabulary([], RANKS) == lm_scoring.public_vocabulary(RANKS)
    rows = spark.createDataFrame([(k, t) for k, t in enumerate([*texts, None])], "doc_id long, text string")
    fitted = lm_scoring.fit_vocabulary(rows, RANKS, len(texts) + 1)
    assert fitted == lm_scoring.fit_vocabulary(rows.repartition(7), RANKS, len(texts) + 1)  # whatever the order
    coded = lm_scoring.encode_texts(rows, RANKS, fitted).collect()
    assert {r["doc_id"]: b"".join(fitted[i] for i in np.frombuffer(r["ids"], "<u2")).decode() for r in coded} == dict(enumerate([*texts, ""]))


def test_vocabulary_is_counted_on_every_character_of_every_text(spark):
    rows = [(k, "plain words of the same kind " * 9) for k in range(2_500)]
    rows += [(2_500 + k, "plain words " * 500 + f"zqxjvkwq{'abcde'[k % 5]} " * 30) for k in range(5)]  # 30 times, behind 6,000 characters
    fitted = lm_scoring.fit_vocabulary(spark.createDataFrame(rows, "doc_id long, text string"), RANKS, len(rows))
    assert fitted == lm_scoring.merged_vocabulary([t for _, t in rows], RANKS)
    assert {b"qa", b"qb", b"qc", b"qd", b"qe"} <= set(fitted)


def test_model_scores_each_id_once():
    p = lm_scoring.initial()
    ids = [[5, 700, 33] * n for n in (0, 1, 9, 60, 4000)]
    together = lm_scoring.text_logp(p, ids)
    for one, both in zip(ids, together, strict=True):
        x, y, _, n = lm_scoring.lay_out([one])
        assert (y >= 0).sum() == len(one) + 1 == n[0]
        assert -lm_scoring._gradients(p, x, y)[0] * n[0] == pytest.approx(both, rel=1e-4)


def test_model_gradients():
    g = np.random.default_rng(0)
    p = {k: (v + g.standard_normal(v.shape) * 0.1).astype(np.float32) for k, v in lm_scoring.initial().items()}
    ids = [g.integers(0, 300, k) for k in (40, 5, 0, 70)]
    x, y, _, n = lm_scoring.lay_out(ids)
    loss = lambda: -lm_scoring.text_logp(p, ids).sum() / n.sum()
    for k, gradient in lm_scoring._gradients(p, x, y)[1].items():
        at = np.unravel_index(np.argmax(np.abs(gradient)), gradient.shape)
        kept = p[k][at]
        p[k][at] = kept + 0.01
        above = loss()
        p[k][at] = kept - 0.01
        assert (above - loss()) / 0.02 == pytest.approx(float(gradient[at]), rel=0.05, abs=2e-4), k  # a step may cross a kink
        p[k][at] = kept


def test_webp_features():
    g = np.random.default_rng(2)
    for h, w, k in ((1, 1, 256), (9, 5, 3), (13, 21, 256)):
        image = g.integers(0, k, (h, w, 4)).astype(np.uint8)
        side = lambda top: g.integers(0, top, (-(-h // 4), -(-w // 4))).astype(np.uint32)  # noqa: B023, E731
        steps = [(), ((webp.SUBTRACT_GREEN,),), ((webp.PREDICTOR, 2, side(14)), (webp.CROSS_COLOUR, 2, side(2**24)))]
        for transforms in steps:
            for cache, references, groups in ((0, False, 0), (4, True, 2)):
                assert (webp.decode(webp.encode(image, transforms, cache, references, groups)) == image).all()
    for n in (1, 2, 4, 16, 200):
        colours = g.integers(0, 256, (n, 4)).astype(np.uint8)
        image = colours[g.integers(0, n, (11, 13))]
        assert (webp.decode(webp.encode(image, ((webp.PALETTE,),), 0, True)) == image).all()


def test_media_columns(spark, odd, empty):
    for r, t in zip(webp.media_columns(odd, keep_media=True).collect(), odd.collect(), strict=True):
        raw = webp.padded((t["text"] or "").encode())
        assert bytes(r["pixels"]) == raw and r["payload_sha256"] == hashlib.sha256(raw).hexdigest()
        assert r["tail_crc32"] == zlib.crc32(raw[-64:]) and r["media_bytes"] == len(r["media"]) and len(raw) % 64 == 0
    assert webp.media_columns(empty).count() == 0


def _single_images(stored):
    at = 0
    while at < len(stored):
        size = 8 + int.from_bytes(stored[at + 4:at + 8], "little")
        yield stored[at:at + size]
        at += size


def test_texts_are_stored_with_references_fitted_codes_and_transforms():
    g = random.Random(5)
    words = [webp.padded("".join(g.choice("qzxj") for _ in range(n)).encode()) for n in (1, 70, 5_000)]
    noise = [webp.padded(g.randbytes(n)) for n in (1, 300, 20_000)]
    again = webp.padded(g.randbytes(4_000) * 9)
    grey = webp.padded(b"".join(bytes((b, b, b, 255)) for b in g.randbytes(3_000)))
    payloads = [*words, *noise, again, grey, bytes(64), bytes(70_016)]
    media = webp.TextMedia()
    stored = media.store(payloads)
    assert media.load(stored) == payloads
    assert [b"".join(webp.decode(i).tobytes() for i in _single_images(s)) for s in stored] == payloads  # by the reader of single images
    assert [media.store([p])[0] for p in payloads] == stored  # whatever stands beside them
    assert len(stored[2]) < 0.3 * len(payloads[2])  # four letters that are rare in prose: 2 bits each, and the heads
    assert len(stored[6]) < 16_000  # 36,000 bytes, which do not shrink but by references within each tile of 16,384
    assert len(stored[7]) < 0.35 * len(payloads[7])  # green subtracted
    assert len(stored[9]) < 500


def test_images_of_other_writers_are_read():
    g = np.random.default_rng(3)
    images = [g.integers(0, 3, (h, w, 4)).astype(np.uint8) for h, w in ((1, 1), (7, 3), (20, 33))]
    forms = [dict(references=True), dict(references=True, cache_bits=3), dict(transforms=((webp.SUBTRACT_GREEN,),), references=True),
             dict(transforms=((webp.PALETTE,),)), dict(group_tile=2)]
    for form in forms:
        stored = [webp.encode(i, **form) for i in images]
        assert webp.TextMedia().load(stored) == [i.tobytes() for i in images]
        with pytest.raises(ValueError):
            webp.TextMedia().load([webp._riff(stored[2][20:60])])


def test_fitted_lengths_are_those_of_huffman():
    g = np.random.default_rng(4)
    counts = (2.0 ** g.uniform(-3, 12, (60, 40))).astype(np.int64)
    counts[0], counts[1], counts[2, 1:] = 0, np.r_[1, np.zeros(39)], 0
    for limit in (7, 11, 15):
        got = webp.fitted_lengths(counts, limit)
        for c, own in zip(counts.tolist(), got.tolist(), strict=True):
            want = webp.limited_lengths(c, limit)
            assert max(own) <= limit and [n > 0 for n in own] == [k > 0 for k in c]
            if limit == 15:
                assert sum(a * b for a, b in zip(c, own, strict=True)) == sum(a * b for a, b in zip(c, want, strict=True))
            if sum(k > 0 for k in c) > 1:
                assert sum(2.0 ** -n for n in own if n) == 1


def test_html(spark):
    page = ("<html><head><title>t</title></head><body><header><h1>Site</h1><a href=x>Home</a></header><div class='cookie-notice'>We use cookies</div>"
            "<div id=content><h2>Title &amp; more</h2><p>First para with wo<b>rd</b> and <a href=y>link</a>.<p>Second  &#233; one &lt;tag&gt;."
            "<ul><li>item one of the list<li>item two</ul><div class=ad-banner>Buy now</div><p>Third paragraph, quite long, of the article text.</div>"
            "<aside>Related stuff</aside><section class=comments><p>Nice article, thank you for it all.</p></section><form><p>Subscribe</p></form><footer>(c)</footer>")
    assert html_extraction.main_text(page) == ("Title & more First para with word and link. Second é one <tag>. item one of the list item two "
                                               "Third paragraph, quite long, of the article text.")
    rows = [(1, "u", None), (2, None, ""), (3, "u", "<p"), (None, "u", page), (4, "u", "<article><p>" + LONG)]
    got = html_extraction.extract_text(spark.createDataFrame(rows, "page_id long, url string, html string")).collect()
    assert [r["n_chars"] for r in got][:3] == [0, 0, 0] and got[4]["text"] == LONG.strip()


def test_minimum_cut_against_brute_force():
    g = random.Random(4)
    for _ in range(200):
        n = g.randint(1, 7)
        scores = [g.uniform(-3, 3) for _ in range(n)]
        edges = [(g.randrange(n), g.randrange(n), g.uniform(0, 2)) for _ in range(2 * n)]
        cost = lambda x: (sum(max(0, s) if not k else max(0, -s) for s, k in zip(scores, x)) + sum(w for a, b, w in edges if x[a] != x[b]))  # noqa: B023, E731
        best = min(cost([bool(m >> i & 1) for i in range(n)]) for m in range(1 << n))
        assert cost(html_extraction.min_cut(scores, edges)) == pytest.approx(best)


def test_mixing(spark, odd, empty):
    assert capped_targets([10, 10, 80], [5, 2, 1], 3) == pytest.approx([30, 30, 40])
    flow = min_cost_flow({"ab": 10.0, "a": 10.0}, {"ab": ["a", "b"], "a": ["a"]}, {"a": 12.0, "b": 8.0}, 3)
    assert sum(v for (p, s), v in flow.items() if s == "a") == pytest.approx(12) and flow[("ab", "b")] == pytest.approx(8)
    got = mix_sources(odd).collect()
    assert len(got) == odd.count() and sorted(map(tuple, got), key=str) == sorted(map(tuple, mix_sources(odd).collect()), key=str)
    for r in got:
        assert r["taken"] <= 3 * r["size"] and r["target"] <= 3 * r["source_size"] + 1e-6
    assert mix_sources(empty).count() == 0


@pytest.mark.parametrize("chunk", [1000, 2])
def test_suffix_dedup(spark, odd, empty, monkeypatch, chunk):
    monkeypatch.setattr(suffix_dedup, "CHUNK_CONTEXTS", chunk)
    g = random.Random(8)
    passage = "".join(g.choice("abcdefgh ") for _ in range(260))
    rows = [(100 + i, "".join(g.choice("klmnop ") for _ in range(g.randint(0, 300))) + passage[g.randint(0, 40):] + "é" * g.randint(0, 3), "en", "a") for i in range(12)]
    docs = odd.where("n_chars is null and (length(text) < 20000 or text is null)").unionByName(table(odd.sparkSession, [*rows, (200, "ab" * 400, "en", "a"), (201, "z" * 199, "en", "a")]))
    raws = [(r["text"] or "").encode() for r in docs.collect()]
    counts = Counter(x[i:i + 200] for x in raws for i in range(len(x) - 199))
    want = []
    for r, x in zip(docs.collect(), raws, strict=True):
        gone = np.zeros(len(x), bool)
        for i in range(len(x) - 199):
            if counts[x[i:i + 200]] > 1:
                gone[i:i + 200] = True
        spans = int((np.diff(np.concatenate([[0], gone.astype(int), [0]])) == 1).sum())
        want.append((r["doc_id"], len(x), int(gone.sum()), spans, hashlib.sha256(np.frombuffer(x, np.uint8)[~gone].tobytes()).hexdigest()))
    assert sorted(map(str, want)) == sorted(str(tuple(r)) for r in suffix_dedup.remove_repeats(docs).collect())
    assert suffix_dedup.remove_repeats(empty).count() == 0


def test_two_stage_order():
    g = random.Random(3)
    for _ in range(200):
        s = bytes(g.choice(b"abc") for _ in range(g.randint(1, 60)))
        order = suffix_dedup.two_stage_order(np.frombuffer(s, np.uint8), 30)
        assert [s[i:i + 30] for i in order] == sorted(s[i:i + 30] for i in range(len(s)))


def test_pipeline_stages(spark, odd, empty):
    import corpus_pipeline as C

    for docs in (odd, empty):
        for name, stage in C.STAGES[:-1]:
            out = stage(spark, docs, "")
            assert out.columns == odd.columns, name
            docs = C.cut(out)
        C.STAGES[-1][1](spark, docs, "").count()
    kept = {r["doc_id"] for r in C.near_dedup_stage(spark, odd, "").collect()}
    assert 4 in kept and 5 not in kept and None in kept


def test_pipeline_against_brute_force(spark, monkeypatch, tmp_path):
    import corpus_pipeline as C

    g = random.Random(11)
    text = lambda n: " ".join("".join(g.choice("abcdefghijklmnop") for _ in range(g.randint(3, 8))) for _ in range(n))
    a, b, c, d, passage = text(90), text(90), text(90), text(90), text(60)
    rows = [(1, a), (1, a), (2, a), (None, a), (3, b), (None, b), (None, b), (None, c), (None, c), (4, d), (5, d.replace(d.split()[40], "other", 1)),
            (6, text(80)), (6, text(80)), (7, text(20) + " " + passage), (8, passage + " " + text(30)), (9, "12 !?"), (10, None), (None, "")]
    docs = table(spark, [(i, t, "en", "a") for i, t in rows])
    docs.write.parquet(str(tmp_path / "documents.parquet"))

    kept: list[tuple] = []
    for i, t in sorted((r for r in rows if any(x.isalpha() for x in r[1] or "")), key=lambda r: (r[0] is None, r[0] or 0)):
        if all(5 * len(shingles(t, 5) & shingles(u, 5)) < 4 * len(shingles(t, 5) | shingles(u, 5)) for _, u in kept):
            kept.append((i, t))
    counts = Counter(t.encode()[k:k + 200] for _, t in kept for k in range(len(t.encode()) - 199))
    cleaned = []
    for i, t in kept:
        x, gone = t.encode(), np.zeros(len(t.encode()), bool)
        for k in range(len(x) - 199):
            if counts[x[k:k + 200]] > 1:
                gone[k:k + 200] = True
        cleaned.append((i, np.frombuffer(x, np.uint8)[~gone].tobytes().decode()))
    assert len(cleaned) == 8 and all(t for _, t in cleaned)

    seen, written = {}, C.cut
    monkeypatch.setattr(C, "cut", lambda df, label: seen.update({label: written(df, label)}) or seen[label])
    got = Counter((r["doc_id"], tuple(r["token_ids"])) for r in C.run(spark, str(tmp_path)).collect())
    assert sorted(((r["doc_id"], r["text"]) for r in seen["stage-suffix_dedup"].collect()), key=str) == sorted(cleaned, key=str)
    uses = {r["doc_id"]: r["uses"] for r in mix_sources(table(spark, [(i, t, "en", "a") for i, t in cleaned]).select("doc_id", "text", "source")).collect()
            if r["doc_id"] is not None}
    library = tiktoken.Encoding("own", pat_str=public_tokenizers.PATTERN, mergeable_ranks=byte_bpe.read_ranks(RANKS), special_tokens={})
    want = Counter((i, tuple(library.encode_ordinary(t))) for i, t in cleaned if i in uses for _ in range(uses[i]))
    assert {k: n for k, n in got.items() if k[0] in uses} == want
    assert {i for i, _ in got} <= {i for i, _ in cleaned}


def test_language_against_brute_force(spark):
    from patternjoin.llm.language_id import GRAM, LanguageFilter

    g = random.Random(3)
    sound = {"aa": "abcde fgh", "bb": "nopqr stu", "cc": "vwxyz éàü"}
    text = lambda l, n: "".join(g.choice(sound[l]) for _ in range(n))
    docs = [(i, text(l, 150), l, "s") for i, l in enumerate(["aa", "bb", "cc"] * 30)]
    model = fit_filter(table(spark, docs))
    held = [(l, text(l, g.randint(30, 200))) for l in ["aa", "bb", "cc"] * 40]
    assert sum(p == l for p, (l, _) in zip(model.decide([t for _, t in held])[0], held, strict=True)) >= 0.98 * len(held)
    # a filter over known n-grams against sets: it never misses one, and what is left after correction is the exact count
    grams = {"aa": {b"abcd", b"bcde"}, "bb": {b"abcd", b"wxyz"}}
    code = lambda x: int.from_bytes(x, "little")
    small = LanguageFilter(["aa", "bb"], {l: np.array([code(x) for x in v], np.uint32) for l, v in grams.items()}, "aa")
    for t in ("abcde", "abcdwxyz", "zzzz", "abcd wxyz", "x" * 500):
        raw = f" {t} ".encode()
        seen = Counter(l for i in range(len(raw) - GRAM + 1) for l in grams if raw[i:i + GRAM] in grams[l])
        total = sum(seen.values())
        (found,), (score,) = small.decide([t])
        want = max(["aa", "bb"], key=lambda l: (seen[l], l == "aa")) if total else "aa"
        assert found == want and score == pytest.approx(seen[want] / total if total else 0.0, abs=1e-3)


def test_html_hard_pages(spark):
    take = html_extraction.main_text
    assert take("<article><header><h1>Head</h1><p>By someone</p></header><p>The text of the article is here and long enough.</p></article>") == (
        "The text of the article is here and long enough.")
    kept = "A paragraph on how engines of this kind rank their results."
    assert kept in take(f"<main><p>First paragraph of the main text, long enough.</p><p class='search-engines'>{kept}</p></main>")
    assert "Buy" not in take("<main><p>First paragraph of the main text, long enough.</p><div class='adBanner'>Buy this now or never</div></main>")
    deep = "<div>" * 3000 + "<p>Deep down there is a paragraph of ordinary length.</p>" + "</div>" * 3000
    assert take(f"<article>{deep}</article>") == "Deep down there is a paragraph of ordinary length."
    schema = "page_id long, url string, html string, text string, n_chars long, key long"
    assert html_extraction.extract_text(spark.createDataFrame([], schema)).count() == 0
    rows = [(i, "u", f"<nav><a href=x>one {i}</a></nav><article><h1>Title {i}</h1><p>Some words of page {i}, enough of them.</p></article><footer>(c) {i}</footer>", "x", 1, 2)
            for i in range(40)]
    got = html_extraction.extract_text(spark.createDataFrame(rows, schema)).collect()
    truth = {i: f"Title {i} Some words of page {i}, enough of them." for i in range(40)}
    f1 = []
    for r in got:  # token F1 against the text that was put in
        a, b = Counter(r["text"].split()), Counter(truth[r["page_id"]].split())
        f1.append(2 * sum((a & b).values()) / (sum(a.values()) + sum(b.values())))
    assert sum(f1) / len(f1) > 0.99


def test_fitted_weights_follow_the_pages(spark):
    # pages whose articles are lists: the start weights speak against lists, the fitted ones must not
    rows = [(i, "u", "<div><p>short</p></div><article>" + "".join(f"<ul><li>entry {j} of list {i} with some more words</li></ul>" for j in range(6)) + "</article>") for i in range(60)]
    pages = spark.createDataFrame(rows, "page_id long, url string, html string")
    w = dict(zip(html_extraction.FEATURES, html_extraction.fit_weights(pages), strict=True))
    assert w["list"] > dict(zip(html_extraction.FEATURES, html_extraction.START, strict=True))["list"] + 0.5
    assert html_extraction.fit_weights(pages.limit(0)) == html_extraction.START


def test_extra_columns_and_empty_tables(spark):
    vec = spark.createDataFrame([(i, [float(i), 1.0], 1, 2, 3) for i in range(120)], "vec_id long, embedding array<float>, score long, q long, slot long")
    assert topk_search.exact_top_k(vec).count() == 15 and topk_search.exact_top_k(vec.limit(0)).count() == 0
    pages = spark.createDataFrame([(1, "u", "x" * 1200, 5, "d"), (2, "u", "x" * 1200, 6, "e")], "page_id long, url string, html string, payload_bytes long, digest string")
    for docs, n in ((pages, 2), (pages.limit(0), 0)):
        archive = warc_archive.new_archive(spark)
        warc_archive.write_archive(docs, archive)
        assert warc_archive.archive_report(spark, archive).count() == n


def test_flow_against_brute_force():
    g = random.Random(6)
    for _ in range(60):
        sources = "abc"[:g.randint(1, 3)]
        members = {f"p{i}": g.sample(sources, g.randint(1, len(sources))) for i in range(g.randint(1, 3))}
        capacity = {p: float(g.randint(0, 3)) for p in members}
        quota = {s: float(g.randint(0, 4)) for s in sources}
        flow = min_cost_flow(capacity, members, quota, 2)

        def all_flows(arcs, left, need):
            if not arcs:
                yield {}
                return
            (p, s), rest = arcs[0], arcs[1:]
            for f in range(int(min(left[p], need[s])) + 1):
                for x in all_flows(rest, left | {p: left[p] - f}, need | {s: need[s] - f}):
                    yield x | {(p, s): f}

        arcs = [(p, s) for p in members for s in members[p]]
        worth = lambda x: (-sum(x.values()), sum(max(0.0, sum(v for (q, _), v in x.items() if q == p) - capacity[p]) for p in members))  # noqa: B023, E731
        best = min(worth(x) for x in all_flows(arcs, {p: 2 * c for p, c in capacity.items()}, quota))
        assert worth(flow) == pytest.approx(best)


def test_repeated_rows_are_one_text(spark):
    docs = table(spark, [(i % 3, f"one two three four five six seven eight nine ten {i % 3 // 2}", "en", "a") for i in range(90)])
    got = near_duplicates(docs, width=2)
    assert got.count() == 90 and {r["component_id"] for r in got.where("doc_id < 2").collect()} == {0}
