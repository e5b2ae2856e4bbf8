"""Secrets, media, token counts, token files and packing against plain versions of the same."""

import hashlib
import io
import random
import re
import wave
import zlib
from collections import Counter, defaultdict

import numpy as np
import public_tokenizers
import pytest
from tokenizers import Tokenizer

from ballspark.llm import bpe, dac, jaccard, media, packing, secret_scan
from ballspark.llm.common import work_dir
from ballspark.llm.token_counts import count_tokens, whole_tokens

PATH = public_tokenizers.path("byte_bpe_50k.json")
LIBRARY = Tokenizer.from_file(PATH)


def ids_of(text):
    return LIBRARY.encode(text or "", add_special_tokens=False).ids


# --- secrets


def plain_base(text):
    assign = r"""(password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)"""
    found = [(m.start(), 0, m.end()) for m in re.finditer(assign, text, re.I | re.A) if len(m[2]) >= 8]
    found += [(m.start(), 1, m.end()) for m in re.finditer(r"AKIA[A-Z0-9]+", text) if len(m[0]) >= 16]
    found += [(m.start(), 2, m.end()) for m in re.finditer(r"[0-9a-f]+", text) if len(m[0]) >= 32]
    return [(("assign", "access", "hex")[k], s, e) for s, k, e in sorted(found)]


def test_spans_equal_the_rules():
    rng = random.Random(4)
    bits = ["password", "PassWd", "api_key", "apikey", "secret", "token", "toKen", ":", "=", " ", '"', "'", "abcdefgh", "0123abcd" * 4, "AKIA", "ABCDEFGHIJKL", "ef", "x", "é", "\n"]
    for _ in range(3000):
        text = "".join(rng.choice(bits) for _ in range(rng.randrange(25)))
        got = [s for s in secret_scan.find_secrets(text.encode()) if s[0] in ("assign", "access", "hex")]
        assert got == plain_base(text), text
    kinds = [k for k, _, _ in secret_scan.find_secrets(b"ghp_" + b"a1B2" * 9 + b" xoxb-1234567890ab eyJabcdefgh.eyJabcdefgh.abcdefghij")]
    assert kinds == ["forge", "chat", "jwt"]


def test_ledger_scans_only_what_is_new(spark, odd_docs):
    ledger = work_dir(spark, "ledger")
    distinct = odd_docs.selectExpr("coalesce(text, '') t").distinct().count()
    assert secret_scan.scan_new(odd_docs, ledger) == distinct
    assert secret_scan.scan_new(odd_docs, ledger) == 0
    more = odd_docs.limit(1).selectExpr("99L as doc_id", "'secret=abcdefghijk' as text")
    assert secret_scan.scan_new(more, ledger) == 1
    found = secret_scan.findings(more, ledger).first()
    assert [(s.kind, s.begin, s.end) for s in found.spans] == [("assign", 0, 18)]


def test_scan_and_redact(spark, odd_docs, no_docs):
    rows = secret_scan.scan_secrets(odd_docs).collect()
    assert len(rows) == odd_docs.count()
    for r in rows:
        assert [tuple(s) for s in r.spans if s.kind in ("assign", "access", "hex")] == plain_base(r.text or "")
    clean = {r.doc_id: r for r in secret_scan.redact(secret_scan.scan_secrets(odd_docs)).collect()}
    assert clean[10].text == "[secret] and token:short [secret] [secret]" and clean[4].text is None and clean[1].id == "own id"
    assert secret_scan.scan_secrets(no_docs).count() == 0


# --- media


def test_sounds_are_lossless(spark, odd_docs, no_docs):
    got = media.sound_features(media.store_sounds(odd_docs)).collect()
    texts = defaultdict(list)
    for r in odd_docs.select("doc_id", "text").collect():
        texts[r.doc_id].append((r.text or "").encode())
    assert len(got) == odd_docs.count()
    by_bytes = defaultdict(set)
    for r in got:
        data = texts[r.id][0]
        payload = data + b"\0" * (max(1, -(-len(data) // 64)) * 64 - len(data))
        assert (r.n_bytes, r.payload_bytes, r.payload_sha256, r.tail_crc32) == (len(data), len(payload), hashlib.sha256(payload).hexdigest(), zlib.crc32(payload[-64:]))
        image = media.to_wav(payload)
        assert (r.media_bytes, r.media_sha256) == (len(image), hashlib.sha256(image).hexdigest())
        with wave.open(io.BytesIO(image)) as w:
            assert (w.getsampwidth(), w.getnchannels(), w.readframes(w.getnframes())) == (1, 1, payload)
        assert list(r.frames) == sorted(r.frames) and len(r.frames) == len(r.codes)
        by_bytes[data].add((tuple(r.frames), tuple(r.codes)))
    assert all(len(v) == 1 for v in by_bytes.values())
    assert media.sound_features(media.store_sounds(no_docs)).count() == 0


def test_fingerprints_find_tones():
    t = np.arange(8192)
    tone = (128 + 60 * np.sin(2 * np.pi * t * 64 / media.WINDOW)).astype(np.uint8).tobytes()
    _, bins = media.peaks(tone)
    assert set(bins.tolist()) <= {0, 64} and 64 in bins  # 0: cutting to whole samples shifts the mean
    noise = np.random.default_rng(0).integers(0, 256, 16384).astype(np.uint8).tobytes()
    whole, part = media.fingerprint(noise), media.fingerprint(noise[media.HOP * 8 :])
    shared = set(zip((whole[0] - 8).tolist(), whole[1].tolist())) & set(zip(part[0].tolist(), part[1].tolist()))
    assert len(shared) > 0.5 * len(part[0])  # a cut sound keeps its codes, eight frames earlier
    assert len(media.fingerprint(b"\x80" * 640)[1]) == 0


def test_long_sounds_are_searched_in_portions(monkeypatch):
    sound = np.random.default_rng(5).integers(0, 256, 40_000).astype(np.uint8).tobytes()
    whole, spectrum = media.fingerprint(sound), media.spectrum(sound)
    assert len(spectrum) == media.frame_count(len(sound)) and np.array_equal(media.spectrum(sound, 10, 30), spectrum[10:30])
    monkeypatch.setattr(media, "FRAMES", 17)
    assert all(np.array_equal(a, b) for a, b in zip(media.fingerprint(sound), whole))


def test_every_sample_is_in_a_frame():
    """Sounds of 704 samples that differ in the last 192 only, and lengths around whole hops."""
    rng = np.random.default_rng(4)
    a, b, c = (rng.integers(0, 256, n).astype(np.uint8).tobytes() for n in (512, 192, 192))
    assert not np.array_equal(media.spectrum(a + b)[-1], media.spectrum(a + c)[-1])
    assert [len(media.spectrum(bytes(n))) for n in (64, 512, 513, 704, 768, 769, 1024)] == [1, 1, 2, 2, 2, 3, 3]
    assert any(not np.array_equal(x, y) for x, y in zip(media.fingerprint(a + b), media.fingerprint(a + c)))


# --- tokens


def test_encoder_equals_the_library():
    e = bpe.Encoder(PATH)
    rng = random.Random(1)
    bits = ["the", " the", "  ", "\n", "\t", "don't", "'ll", "_", "__x", "9", "²", "٣", "é", "中", "\U0001f600", "<|endoftext|>", "<|", "\x1c", "\x85", "\xa0", "　", "...", "A", "́", "é", "123abc", "'", "s", "$%"]
    texts = ["".join(rng.choice(bits) for _ in range(rng.randrange(30))) for _ in range(3000)] + ["a" * 5000, " " * 500, ""]
    for text, got in zip(texts, e.encode(texts)):
        assert got == np.array(LIBRARY.encode(text, add_special_tokens=False).ids, e.dtype).tobytes(), repr(text)


def test_encoder_forgets_and_cuts_long_texts(monkeypatch):
    monkeypatch.setattr(bpe, "CACHE", 6000)  # of which more stay than a new table has room for
    e = bpe.Encoder(PATH)
    rng = random.Random(3)
    for _ in range(6):
        text = " ".join("".join(rng.choice("abcdefgh") for _ in range(6)) for _ in range(2500))
        assert e.encode([text])[0] == np.array(LIBRARY.encode(text, add_special_tokens=False).ids, e.dtype).tobytes()
    assert e.table.n <= 8500
    monkeypatch.setattr(bpe, "CACHE", 300)
    monkeypatch.setattr(bpe, "TOGETHER", 500)
    e = bpe.Encoder(PATH)
    texts = [" ".join("".join(rng.choice("abcé'1 \n") for _ in range(rng.randrange(1, 9))) for _ in range(n)) for n in (3, 2000, 0, 900, 1, 40)] + ["a" * 3000, "  \n " * 700]
    for text, got in zip(texts, e.encode(texts)):
        assert got == np.array(LIBRARY.encode(text, add_special_tokens=False).ids, e.dtype).tobytes()
    assert e.table.n <= 700
    assert list(bpe.stretches_of("ab cd", 1)) == ["ab", " cd"] and "".join(bpe.stretches_of(texts[1], 100)) == texts[1]


def test_counts(spark, odd_docs, no_docs):
    whole = whole_tokens(PATH)
    assert " the" in whole and len(whole) > 40_000
    got = count_tokens(odd_docs, PATH).collect()
    want = Counter((r.doc_id, len((r.text or "").encode()), len(ids_of(r.text))) for r in odd_docs.collect())
    assert Counter((r.id, r.n_bytes, r.n_tokens) for r in got) == want
    assert all(r.n_whole <= r.n_tokens for r in got)
    assert count_tokens(no_docs, PATH).count() == 0


def test_codes_round_trip():
    rng = np.random.default_rng(0)
    for ids in (np.zeros(0, int), np.array([0]), np.array([255, 256, 65535, 1 << 20, (1 << 31) - 1]), rng.integers(0, 50257, 3000), rng.integers(0, 200, 1000)):
        assert (dac.decode_levels(dac.encode_levels(ids), len(ids)) == ids).all()


class Bytes(io.BytesIO):
    def size(self):
        return len(self.getvalue())


def test_random_access(monkeypatch):
    monkeypatch.setattr(dac, "SEGMENT", 700)
    rng = np.random.default_rng(3)
    docs = [(i, (rng.pareto(0.5, rng.integers(0, 900)) * 5).clip(0, 50256).astype(np.uint32)) for i in range(20)] + [(None, np.array([7]))]
    stream = Bytes()
    out = dac.Writer(stream)
    for d, ids in docs:
        out.add(d, ids)
    out.close()
    reader, every = dac.Reader(stream), np.concatenate([ids for _, ids in docs])
    assert len(reader.segments) > 3
    start = 0
    for (d, ids), (e, before, back) in zip(docs, reader.documents()):
        assert d == e and before == start and (ids == back).all()
        start += len(ids)
    assert [reader.token(i) for i in range(0, len(every), 7)] == every[::7].tolist()
    with pytest.raises(ValueError):
        dac.Reader(Bytes(b"x" * 100))


def test_token_files(spark, odd_docs, no_docs):
    folder = dac.token_file_folder(spark)
    got = dac.read_tokens(dac.write_tokens(odd_docs, folder, PATH, end_id=2), folder).orderBy("start").collect()
    assert [r.id for r in got] == sorted([r.doc_id for r in odd_docs.collect()], key=lambda i: (i is not None, i or 0))
    start, texts = 0, {r.doc_id: r.text for r in odd_docs.collect()}
    for r in got:
        want = np.array([*ids_of(texts[r.id]), 2], "<u4")
        assert r.start == start and r.n == len(want) and bytes(r.ids) == want.tobytes()
        start += len(want)
    folder = dac.token_file_folder(spark)
    assert dac.read_tokens(dac.write_tokens(no_docs, folder, PATH, end_id=2), folder).count() == 0


# --- packing


def check_pieces(rows, want):
    """``want``: a list of id lists by document; rows with one id are told apart by their ids."""
    pieces, windows = defaultdict(list), defaultdict(list)
    for r in rows:
        windows[r.sequence_id].append((r.offset, r.length))
        pieces[r.doc_id].append((r.start, np.frombuffer(r.ids, "<u4").tolist(), r.doc_tokens))
    for w in windows.values():
        at = 0
        for offset, n in sorted(w):
            assert offset == at and n > 0
            at += n
        assert at <= packing.WINDOW
    for d, lists in want.items():
        flat = Counter((s + i, x) for s, ids, _ in pieces[d] for i, x in enumerate(ids))
        assert flat == Counter((i, x) for ids in lists for i, x in enumerate(ids))
        assert {t for _, _, t in pieces[d]} == {len(ids) for ids in lists}
    return windows


def test_packing(spark, odd_docs, no_docs):
    want = defaultdict(list)
    for r in odd_docs.collect():
        want[r.doc_id].append([*ids_of(r.text), 1])
    check_pieces(packing.pack(odd_docs, PATH, 1).collect(), want)
    assert packing.pack(no_docs, PATH, 1).count() == 0


@pytest.mark.parametrize("lengths", [[1500] * 300, [2047] * 50, [1] * 5000, list(range(1, 2048)), [1024] * 101, [300] * 1000, []])
def test_windows_are_full(lengths):
    hist = Counter(-(-n // packing.UNIT) for n in lengths)
    windows = packing.fill(lengths, packing.plan(hist) if lengths else [])
    used = defaultdict(list)
    for w in windows:
        assert sum(n for _, _, n in w) <= packing.WINDOW
        for i, begin, n in w:
            used[i].append((begin, n))
    for i, n in enumerate(lengths):
        at = 0
        for begin, size in sorted(used[i]):
            assert begin == at
            at += size
        assert at == n
    if lengths:
        assert len(windows) <= sum(lengths) / packing.WINDOW * 1.02 + 1


def test_least_squares_meet_the_histogram():
    columns = packing.combinations()
    assert (columns.sum(axis=1) == packing.CLASSES).all() and len({tuple(c) for c in columns}) == len(columns)
    h = np.bincount(np.random.default_rng(2).integers(1, packing.CLASSES + 1, 20_000), minlength=packing.CLASSES + 1)[1:].astype(float)
    x = packing.nnls(columns, h)
    met = np.zeros(packing.CLASSES + 1)
    for slot in columns.T:
        np.add.at(met, slot, x)
    assert (x >= 0).all() and np.abs(met[1:] - h).sum() < 0.1 * h.sum()


def test_word_hashes_are_the_words():
    """Words as a plain split finds them, equal hashes for equal words only, also of words longer than the lanes and with zero bytes."""
    rng = np.random.default_rng(5)
    texts = [b"", b" ", b"One oNE\tone\x0bO", b"a a\x00 a\x00\x00 \xc2\xa0 x\x1fy", b"tail ", " Ärger ärger ".encode()]
    texts += [bytes(rng.choice(list(b"aB \n\r\x0c\x00"), int(rng.integers(300))).astype(np.uint8)) for _ in range(200)]
    texts += [b" ".join(b"w" * k + b"x" + b"w" * (j - k) for j in (7, 8, 15, 16, 24, 31, 32, 40) for k in range(j + 1))]
    words = [t.lower().split() for t in texts]
    hashes, counts = jaccard.word_hashes(texts)
    flat = [w for of in words for w in of]
    assert counts.tolist() == [len(w) for w in words] and len(hashes) == len(flat)
    assert len(set(zip(flat, hashes.tolist()))) == len(set(flat)) == len(set(hashes.tolist()))
    assert len(jaccard.word_hashes([])[0]) == 0
    kept, n = jaccard.tallied(*jaccard.tallied(hashes[:0], np.empty(0, np.int64), hashes[:900]), hashes[900:])
    assert dict(zip(kept.tolist(), n.tolist())) == Counter(hashes.tolist())


def test_magnitudes_are_found_by_first_bits():
    known = np.sort(np.concatenate([np.arange(1, 40, dtype=np.uint64), np.random.default_rng(6).integers(1 << 63, size=5000, dtype=np.uint64)]))
    of = jaccard.Magnitudes(known, (np.arange(len(known)) % 60 + 1).astype(np.uint8)).of
    assert of(known).tolist() == (np.arange(len(known)) % 60 + 1).tolist()
    assert not of(known[:100] + np.uint64(1 << 40)).any()
    assert not jaccard.Magnitudes(known[:0], np.empty(0, np.uint8)).of(known).any()
