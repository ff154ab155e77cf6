"""Values, not only rows: odd rows against plain versions, and the classifier against a plain one."""

import hashlib
import math
import re
import zlib

import pytest
import xxhash
from test_bruteforce import THEIRS, plain_base, plain_components

from semrank.exec.scratch import Scratch
from semrank.llm import bpe, license_scan, line_dedup, merkle, mixing, near_dup, quality_classifier, quality_rules, secret_scan, token_counts
from semrank.llm.text import load

SF = "/root/testdata/sf0.001"
BLANK = "\x20\t\n\x0b\x0c\r"


def words(t):
    return re.findall(f"[^{BLANK}]+", t or "")


def by_id(rows):
    out = {}
    for r in rows:
        out.setdefault(r["doc_id"], []).append(r)
    return out


@pytest.fixture(scope="module")
def texts(odd_docs):
    return [(r.doc_id, r.text) for r in odd_docs.select("doc_id", "text").collect()]


def test_rules(odd_docs, texts):
    got = by_id(quality_rules.quality_rules(odd_docs).collect())
    for i, t in texts:
        w, r = words(t), got[i][0]
        lines = [x for x in (t or "").split("\n") if words(x)]
        five = [tuple(w[k : k + 5]) for k in range(len(w) - 4)]
        hit = {k + j for k, x in enumerate(five) if five.count(x) > 1 for j in range(5)} if len(w) < 1000 else None
        assert (r.n_words, r.word_chars, r.n_symbols) == (len(w), sum(map(len, w)), sum(c in "#*$%&|<>" for c in t or ""))
        assert r.n_dup_lines == len(lines) - len(set(lines))
        if hit is not None:
            assert r.n_repeat_words == len(hit) and r.base_failed == (len(w) < 10 or 100 * len(hit) > 20 * len(w))
            assert not (r.base_failed and r.kept)


def test_secrets(odd_docs, texts):
    got = by_id(secret_scan.secret_scan(odd_docs).collect())
    for i, t in texts:
        base = ",".join(f"{k}:{s}:{e}" for k, s, e in plain_base(t or ""))
        assert got[i][0].base_sha256 == hashlib.sha256(base.encode()).hexdigest()


def test_near(odd_docs, texts):
    want = plain_components({i: t for i, t in texts if i is not None})
    for r in near_dup.near_duplicates(odd_docs).collect():
        if r.doc_id is None:
            assert (r.component_id, r.kept) == (None, True)
        else:
            assert (r.n_shingles, r.component_id, r.kept) == (*want[r.doc_id], want[r.doc_id][1] == r.doc_id)


def test_mix(odd_docs):
    rows = mixing.mix_counts(odd_docs).collect()
    docs = {(r.doc_id, r.text): r.source for r in odd_docs.select("doc_id", "text", "source").collect()}
    sizes = {}
    for (i, t), s in docs.items():
        n = 2 if i == 7 else 1
        sizes[s] = sizes.get(s, 0) + n * len(words(t))
    order = sorted((s for s in sizes if s is not None)) + [None] * (None in sizes)
    weight, total, target = {s: k % 3 + 1 for k, s in enumerate(order)}, sum(sizes.values()), {}
    free = set(order)
    while True:
        left = total - sum(target.values())
        share = {s: left * weight[s] / sum(weight[x] for x in free) for s in free}
        over = [s for s in free if share[s] >= 3 * sizes[s]]
        if not over:
            target |= share
            break
        for s in over:
            target[s] = 3 * sizes[s]
            free.discard(s)
        if not free:
            break
    source = {i: s for (i, _), s in docs.items()}
    for r in rows:
        s = source[r.doc_id]
        assert r.source_size == sizes[s] and math.isclose(r.target, target[s], rel_tol=1e-9, abs_tol=1e-9)
        assert r.taken % max(r["size"], 1) == 0 and r.taken <= 3 * r["size"]


def test_tokens(odd_docs, texts):
    got = by_id(bpe.encode_digests(odd_docs).collect())
    for i, t in texts:
        ids = THEIRS.encode_ordinary(t or "")
        assert (got[i][0].n_tokens, got[i][0].decoded_sha256) == (len(ids), hashlib.sha256((t or "").encode()).hexdigest())


def test_prints(odd_docs, texts):
    rows = sorted(texts, key=lambda x: (x[0] is not None, x[0] or 0))
    got = by_id(merkle.fingerprints(odd_docs).collect())
    for (i, t), (_, after) in zip(rows, [*rows[1:], rows[0]], strict=True):
        t, after = t or "", after or ""
        k = len(t) // 4
        edited = hashlib.sha256((t[: len(t) - k] + after[:k]).encode()).hexdigest()
        assert edited in {r.edited_sha256 for r in got[i]} and {r.n_chars for r in got[i]} == {len(t)}
    prints = {}
    for i, t in rows:
        prints.setdefault(t or "", set()).update(r.fingerprint for r in got[i])
    assert all(len(x) == 1 for x in prints.values()) and len({next(iter(x)) for x in prints.values()}) == len(prints)


def test_counts(odd_docs):
    got = sorted((str(r.source), str(r.lang), r.version, r.n_docs, r.n_tokens) for r in token_counts.maintain(odd_docs, Scratch(odd_docs.sparkSession, "t").root).collect())
    want = {}
    for r in odd_docs.select("source", "lang", "text").collect():
        if len(words(r.text)) >= 10:
            for version, n in (("words-1", len(words(r.text))), ("bytes-4", -(-len(r.text.encode()) // 4))):
                was = want.get((str(r.source), str(r.lang), version), (0, 0))
                want[str(r.source), str(r.lang), version] = (was[0] + 1, was[1] + n)
    assert got == sorted((*k, *v) for k, v in want.items())


def test_lines_and_licences(odd_docs, texts):
    lines = by_id(line_dedup.dedup_lines(odd_docs, counts=True).collect())
    assert lines[9][0].text == "a start" and lines[8][0].n_lines_removed == 0 and lines[2][0].text is None and lines[3][0].text == ""
    assert all(r.text == t for i, t in texts if i != 9 for r in lines[i])
    assert {r.licenses for r in license_scan.license_scan(odd_docs).collect()} == {""}


# ---- the classifier ------------------------------------------------------------------------------------------------------


def features(text):
    """id -> value by loops; hashes are the operator's, arithmetic is plain."""
    q, m64 = quality_classifier, 2**64
    odd = [int(x) for x in q.ODD]
    pieces = re.findall(r"[^\W_]+|[^\w\s]+|_+", text or "")
    lex = [xxhash.xxh32_intdigest(p.lower().encode("utf-8", "surrogatepass")) for p in pieces]
    form = [xxhash.xxh32_intdigest(q.shape(p).encode("utf-8", "surrogatepass"), 7) for p in pieces]
    both = list(zip(lex, form, strict=True))
    form = [f + (k > 0 and both[k] == both[k - 1]) for k, f in enumerate(form)]
    slot = lambda x, k: (x * odd[k] % m64) >> 46
    forms = [(a * odd[2] + b) % m64 for a, b in zip(form, form[1:], strict=False)]
    kinds = [[slot(x + 1, 0) for x in lex] + [slot((a * odd[1] + b) % m64, 0) for a, b in zip(lex, lex[1:], strict=False)], [slot(x, 1) for x in forms], [slot((a * odd[0] + b) % m64, 2) for a, b in zip(forms, form[2:], strict=False)]]
    out = {q.DIM: 1.0}
    for ids in kinds:
        for i in ids:
            out[i] = out.get(i, 0.0) + q.SCALE / len(ids)
    return out


def plain_ftrl(rows):
    """Follow the regularised leader, coordinate by coordinate."""
    q, z, n = quality_classifier, {}, {}

    def weight(i):
        zi = z.get(i, 0.0)
        return 0.0 if abs(zi) <= q.L1 else -(zi - math.copysign(q.L1, zi)) / ((q.BETA + math.sqrt(n.get(i, 0.0))) / q.ALPHA + q.L2)

    for _ in range(q.EPOCHS):
        for x, y in rows:
            w = {i: weight(i) for i in x}
            p = 1 / (1 + math.exp(-max(-30, min(30, sum(w[i] * v for i, v in x.items())))))
            for i, v in x.items():
                g, old = (p - y) * v, n.get(i, 0.0)
                z[i] = z.get(i, 0.0) + g - (math.sqrt(old + g * g) - math.sqrt(old)) / q.ALPHA * w[i]
                n[i] = old + g * g
    return weight


def test_scores_are_those_of_a_plain_learner(spark):
    docs = {r.doc_id: r.text for r in load(spark, SF, "documents").collect()}
    labels = {r.doc_id: r.quality for r in load(spark, SF, "labels").collect()}
    learnt = sorted((i for i in labels if i in docs and zlib.crc32(str(i).encode()) % 5), key=lambda i: xxhash.xxh64_intdigest(str(i)))
    weight = plain_ftrl([(features(docs[i]), labels[i]) for i in learnt])
    got = {r.doc_id: r for r in quality_classifier.classify(load(spark, SF, "documents"), load(spark, SF, "labels")).collect()}
    assert set(got) == set(docs)
    for i, t in docs.items():
        want = 1 / (1 + math.exp(-sum(weight(k) * v for k, v in features(t).items())))
        assert got[i].score == pytest.approx(want, abs=2e-3) and got[i].held_out == (zlib.crc32(str(i).encode()) % 5 == 0)
        assert got[i].predicted == int(got[i].score >= 0.3)


def test_bounded_steps(monkeypatch):
    """States that are not kept, and forgetting all of them, change no token."""
    want = bpe.ByteBpe(bpe.ranks_of(None))
    texts = [f"Zq{i * 7919 % 1000}xv plain words, überlange Wörter {i} und 数{i}据 αβγ{i}" for i in range(60)]
    monkeypatch.setattr(bpe, "STEPS", 40)
    monkeypatch.setattr(bpe, "MEMO", 30)
    got = bpe.ByteBpe(bpe.ranks_of(None))
    for _ in range(2):
        for t in texts:
            assert got.encode(t) == want.encode(t)
            assert len(got.pieces) + len(got.pieces.older) <= 34 and got.transducer.n_steps <= 40
