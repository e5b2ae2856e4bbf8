"""The registered queries on the smallest tables: every column that is promised, against plain versions of the whole contract."""

import hashlib
import io
import math
import wave
import zlib
from collections import Counter, defaultdict

import numpy as np
import pyarrow.parquet as pq
import pytest
from tests.conftest import SF

from ballspark.llm import jaccard, media, packing, quality, secret_scan, token_counts
from ballspark.llm.queries import QUERIES, TOKENIZER

from .conftest import DOCS
from .test_corpus import plain_components, plain_measures
from .test_texts import ids_of, plain_base


@pytest.fixture(scope="session")
def docs(sf_dir):
    rows = pq.read_table(f"{sf_dir}/documents.parquet").to_pylist()
    assert len({r["doc_id"] for r in rows}) == len(rows)
    return {r["doc_id"]: r for r in rows}


def answers(spark, name, sf_dir=SF):
    return QUERIES[name](spark, sf_dir).collect()


def by_doc(rows, docs):
    assert sorted(r.doc_id for r in rows) == sorted(docs)
    return {r.doc_id: r for r in rows}


def spans_text(spans):
    return ",".join(f"{k}:{s}:{e}" for k, s, e in spans)


def test_secrets(spark, docs):
    for i, r in by_doc(answers(spark, "op2_secret_scan"), docs).items():
        base = plain_base(docs[i]["text"] or "")
        n = Counter(k for k, _, _ in base)
        assert (r.n_assign, r.n_access, r.n_hex) == (n["assign"], n["access"], n["hex"])
        assert r.base_sha256 == hashlib.sha256(spans_text(base).encode()).hexdigest()
        spans = [s for s in r.spans.split(",") if s]
        assert not Counter(spans_text(base).split(",") if base else []) - Counter(spans)
        assert [int(s.split(":")[1]) for s in spans] == sorted(int(s.split(":")[1]) for s in spans)


def test_media(spark, docs):
    seen = {}
    for i, r in by_doc(answers(spark, "op3_media_columns"), docs).items():
        data = (docs[i]["text"] or "").encode()
        payload = data + bytes(max(1, -(-len(data) // 64)) * 64 - len(data))
        image = io.BytesIO()
        with wave.open(image, "wb") as w:
            w.setparams((1, 1, media.RATE, 0, "NONE", ""))
            w.writeframes(payload)
        image = image.getvalue()
        assert (r.n_bytes, r.payload_bytes, r.payload_sha256, r.tail_crc32) == (len(data), len(payload), hashlib.sha256(payload).hexdigest(), zlib.crc32(payload[-64:]))
        assert (r.media_bytes, r.media_sha256) == (len(image), hashlib.sha256(image).hexdigest())
        assert r.frames == sorted(r.frames) and len(r.frames) == len(r.codes) and seen.setdefault(payload, r.feature) == r.feature
        assert r.feature.split(":")[0] == str(len(r.codes))
    assert len(set(seen.values())) > 0.9 * len(seen)


def test_packing(spark, docs):
    pieces, windows, ids = defaultdict(list), defaultdict(list), {}
    rows = answers(spark, "op4_packing")
    for r in rows:
        pieces[r.doc_id].append((r.start, r.length))
        windows[r.sequence_id].append((r.offset, r.length))
        if r.doc_id not in ids:
            ids[r.doc_id] = np.array([*ids_of(docs[r.doc_id]["text"]), 1], "<u4")
        assert r.doc_tokens == len(ids[r.doc_id]) and r.ids_crc32 == zlib.crc32(ids[r.doc_id][r.start : r.start + r.length].tobytes())
    assert pieces.keys() == docs.keys()
    for held, whole in [*((pieces[i], len(ids[i])) for i in docs), *((w, None) for w in windows.values())]:
        at = 0
        for begin, n in sorted(held):
            assert begin == at and n > 0
            at += n
        assert at == whole if whole is not None else at <= 2048
    assert sum(len(x) for x in ids.values()) > 0.97 * 2048 * len(windows)


def test_token_files_and_counts(spark, docs):
    start, got, counts = 0, by_doc(answers(spark, "op5_token_files"), docs), by_doc(answers(spark, "op9_token_counts"), docs)
    for i in sorted(docs):
        text = docs[i]["text"] or ""
        ids = np.array([*ids_of(text), 2], "<u4")
        r, c = got[i], counts[i]
        assert (r.start, r.n_tokens, r.ids_crc32) == (start, len(ids), zlib.crc32(ids.tobytes()))
        assert (c.n_bytes, c.n_tokens, c.over_limit) == (len(text.encode()), len(ids) - 1, len(ids) - 1 > 1024)
        start += len(ids)


def test_quality(spark, docs):
    rows = by_doc(answers(spark, "op6_quality_rules"), docs)
    judged = {r.row.doc_id: r for r in quality.judge(spark.read.parquet(f"{SF}/documents.parquet"), keep=["doc_id"]).collect()}
    for i, r in rows.items():
        m = plain_measures(docs[i]["text"] or "")
        assert (r.n_words, r.word_chars, r.n_symbols, r.n_dup_lines, r.n_repeat_words) == m
        assert r.base_failed == (m[0] < 50 or 100 * m[4] > 50 * m[0])
        j = judged[i]
        room = quality.SHORT / math.sqrt(max(1, m[1]))
        inside = j.lower is None or j.lower - room <= r.log_perplexity <= j.upper + room
        assert r.kept == (not r.base_failed and inside) and math.isclose(j.log_perplexity, r.log_perplexity, rel_tol=1e-9)


def test_components(spark, docs):
    want = plain_components([(i, d["text"]) for i, d in docs.items()])
    assert {i: (r.n_shingles, r.component_id) for i, r in by_doc(answers(spark, "op7_jaccard_join"), docs).items()} == want


def test_mixture(spark, docs):
    """Weights, the exponent by bisection, and each document's rounds, from the documents' own token counts."""
    tokens = {i: len(ids_of(d["text"])) + 1 for i, d in docs.items()}
    share, whole = Counter(), sum(tokens.values())
    for i, d in docs.items():
        share[d["source"]] += tokens[i] / whole

    def repeats(a):
        total = sum(p**a for p in share.values())
        return {s: 1.5 * p ** (a - 1) / total for s, p in share.items()}

    low, high = 0.0, 1.0
    for _ in range(60):
        mid = (low + high) / 2
        low, high = (low, mid) if max(repeats(mid).values()) <= 2.0 else (mid, high)
    want = repeats(high)
    rows = answers(spark, "op8_mixing")
    times, taken = Counter(r.doc_id for r in rows), Counter()
    assert len({(r.doc_id, r.mix_epoch) for r in rows}) == len(rows)
    for r in rows:
        d = docs[r.doc_id]
        assert r.source == d["source"] and r.mix_tokens == tokens[r.doc_id] and math.isclose(r.mix_weight, want[r.source] * share[r.source] / 1.5, rel_tol=1e-4)
        taken[r.source] += r.mix_tokens
    for i, d in docs.items():
        assert times[i] in (math.floor(want[d["source"]]), math.floor(want[d["source"]]) + 1) or abs(want[d["source"]] - round(want[d["source"]])) < 1e-4
    longest = {s: max(tokens[i] for i, d in docs.items() if d["source"] == s) for s in share}
    assert all(abs(taken[s] - want[s] * share[s] * whole) <= longest[s] for s in share)


def test_pipeline_of_the_given_documents(spark, docs, sf_dir):
    """Every stage's decisions by plain rules on its own input; then the pieces of what is left."""
    import corpus_pipeline as cp

    now, seen = spark.read.parquet(f"{sf_dir}/documents.parquet"), []
    for _, stage in cp.STAGES:
        now = cp.written(stage(spark, now, sf_dir), "stage")
        seen.append([r.asDict() for r in now.collect()])
    good, one, clean, mixed, pieces = seen
    kept = {r.row.doc_id for r in quality.judge(spark.read.parquet(f"{sf_dir}/documents.parquet"), keep=["doc_id"]).where("kept").collect()}
    assert {r["doc_id"] for r in good} == kept and all(r == docs[r["doc_id"]] for r in good)
    linked = plain_components([(r["doc_id"], r["text"]) for r in good])
    assert sorted(r["doc_id"] for r in one) == sorted(i for i, (_, c) in linked.items() if c == i)
    for r in clean:
        assert not plain_base(r["text"]) and (r["text"] == docs[r["doc_id"]]["text"] or r["n_chars"] == len(r["text"]))
    assert {r["doc_id"] for r in clean} == {r["doc_id"] for r in one} == {r["doc_id"] for r in mixed}
    texts, times = {r["doc_id"]: r["text"] for r in clean}, Counter(r["doc_id"] for r in mixed)
    assert all(r["text"] == texts[r["doc_id"]] for r in mixed)
    got = Counter()
    for p in pieces:
        ids = np.array([*ids_of(texts[p["doc_id"]]), cp.END_ID], "<u4")
        assert p["doc_tokens"] == len(ids) and bytes(p["ids"]) == ids[p["start"] : p["start"] + p["length"]].tobytes()
        got[p["doc_id"]] += p["length"]
    assert got == Counter({i: n * (len(ids_of(texts[i])) + 1) for i, n in times.items()})


def test_very_long_texts(spark):
    """Two near copies of 1.5 million characters, one beginning with, one ending in a secret, through every operator on texts."""
    rng = np.random.default_rng(9)
    words = [f"w{k}" if k % 7 else f"Wörter{k}," for k in rng.integers(0, 60_000, 230_000).tolist()]
    texts = {1: " ".join(words), 2: " ".join([*words[:-3], "token=abcdefghijkl"]), 3: None}
    docs = spark.createDataFrame([(i, t, "en", "a", 0) for i, t in texts.items()], DOCS)
    counts = {r.id: r for r in token_counts.count_tokens(docs, TOKENIZER).collect()}
    found = {r.doc_id: [tuple(x) for x in r.spans] for r in secret_scan.scan_secrets(docs).collect()}
    judged = {r.row.doc_id: r for r in quality.judge(docs, keep=["doc_id"]).collect()}
    linked = {r.doc_id: r for r in jaccard.link_components(docs).collect()}
    sounds = {r.id: r for r in media.sound_features(media.store_sounds(docs)).select("id", "payload_bytes", "payload_sha256").collect()}
    pieces = Counter()
    for r in packing.pack(docs, TOKENIZER, 1).select("doc_id", "length").collect():
        pieces[r.doc_id] += r.length
    for i, t in texts.items():
        data = (t or "").encode()
        payload = data + bytes(max(1, -(-len(data) // 64)) * 64 - len(data))
        assert counts[i].n_tokens == len(ids_of(t)) == pieces[i] - 1 and counts[i].n_bytes == len(data)
        assert found[i] == plain_base(t or "")
        assert judged[i].n_words == len((t or "").split()) and judged[i].word_chars == len("".join((t or "").split()))
        assert (sounds[i].payload_bytes, sounds[i].payload_sha256) == (len(payload), hashlib.sha256(payload).hexdigest())
    assert linked[1].component_id == linked[2].component_id == 1 and linked[3].component_id == 3 and linked[1].n_shingles > 200_000


def test_url_rules_are_the_contracts(spark, tmp_path):
    """Each rule of the contract's list decides a url with the verdict that the list gives it."""
    rules = {"com/en/": "block", "example.com/en/7": "allow", "net/de/": "allow", "example.net/de/8": "block", "org/es/": "block"}
    urls = ["http://a.com/en/1", "http://www.example.com/en/70", "http://a.NET/de/x?q", "https://net/de/", "http://m.example.net/de/8", "http://example.net/de/9", "http://org/es/#x"]
    pages = [(i, u, "") for i, u in enumerate(urls)]
    spark.createDataFrame(pages, "page_id long, url string, html string").write.parquet(f"{tmp_path}/pages.parquet")
    got = {r.page_id: (r.rule, r.verdict) for r in answers(spark, "op1_url_filters", str(tmp_path))}
    fits = ["com/en/", "example.com/en/7", "net/de/", "net/de/", "example.net/de/8", "net/de/", "org/es/"]
    assert got == {i: (rule, rules[rule]) for i, rule in enumerate(fits)}
