"""Formatting, encoding, extraction, personal data, scores, fingerprints and mixing."""

import collections
import hashlib
import math
import random
import re
import time
import zlib

import numpy as np
import pyarrow as pa
import pytest
import xxhash
from pyspark.sql import functions as F

import corpus_pipeline as C
from shapesig.llm import chat_tree, html_crf, improbable_digest, pareto_mix, pii_anchors, piece_dropout, quality_qda
from shapesig.llm import entries
from shapesig.llm.kernels import mixed
from tests_llm_data import DATA, docs

CONTROL = ["\\", "<s>", "</s>", "[INST]", "[/INST]", "<<SYS>>", "<</SYS>>", "<|", "|>", "|", "<", " ", "\n", "a", " [/INST]", "\n<</SYS>>\n\n", " </s>"]


def test_template_is_reversible():
    rng = random.Random(5)
    for _ in range(3000):
        turns = [(rng.choice(["user", "assistant", "system", "tool", "x|>y", "", "a\\b"]), "".join(rng.choice(CONTROL) for _ in range(rng.randint(0, 8)))) for _ in range(rng.randint(0, 4))]
        text = "<s>" + "".join("".join(chat_tree.form(r, t)) for r, t in turns)
        assert [(r, t) for r, t, _, _ in chat_tree.parse(text)] == turns


def test_a_long_turn_is_parsed_in_one_scan():
    text = "\\" * 100_000 + "ab [/INST] </s> <s>" * 200_000
    formatted = "<s>" + "".join("".join(chat_tree.form(r, text)) for r in ("user", "x\\", "assistant"))
    began = time.process_time()
    assert [(r, t) for r, t, _, _ in chat_tree.parse(formatted)] == [(r, text) for r in ("user", "x\\", "assistant")]
    assert time.process_time() - began < 30


def conversations(spark, rows):
    return spark.createDataFrame(rows, "conv_id long, turn long, role string, text string")


def test_tree_shares_turns_and_reads_back(spark):
    rows = []
    for c in range(60):
        rows += [(c, 0, "system", "be kind"), (c, 1, "user", f"q{c % 3}"), (c, 2, "assistant", f"a{c % 2}"), (c, 3, "user", f"own {c}")]
    rows += [(100, 0, None, None), (101, 1, "assistant", ""), (None, 0, "user", "no id"), (102, 0, "user", "x" * 30_000)]
    df = conversations(spark, rows)
    blocks = chat_tree.pack(df, block=2000)
    assert blocks.agg(F.sum(F.length("tokens"))).first()[0] < sum(len("".join(chat_tree.form(r or "", t or ""))) for _, _, r, t in rows)
    got = {r.conv_id: r for r in chat_tree.read_back(blocks).collect()}
    by = collections.defaultdict(list)
    for c, k, r, t in rows:
        by[c].append((k, r or "", t or ""))
    assert set(got) == set(by)
    for c, turns in by.items():
        turns.sort()
        said = "".join(f"{r}\n{t}\n" for _, r, t in turns)
        learned = "".join(t for _, r, t in turns if r == "assistant")
        formatted = "<s>" + "".join("".join(chat_tree.form(r, t)) for _, r, t in turns)
        assert (got[c].n_turns, got[c].turns_sha256, got[c].loss_chars, got[c].loss_sha256, got[c].formatted_chars) == (len(turns), hashlib.sha256(said.encode()).hexdigest(), len(learned), hashlib.sha256(learned.encode()).hexdigest(), len(formatted))
    assert chat_tree.read_back(chat_tree.pack(conversations(spark, []))).count() == 0


def test_positions_and_attention_follow_the_path(spark):
    row = chat_tree.pack(conversations(spark, [(c, k, r, f"{t}{c if k else ''}") for c in range(3) for k, r, t in ((0, "user", "same"), (1, "assistant", "own"))])).collect()
    for b in row:
        for node, parent in enumerate(b.node_parent):
            before = sum(x.end - x.start for x in b.attend[parent]) if parent >= 0 else 0
            assert b.node_position[node] == before and b.attend[node][-1].end > b.node_start[node]
        every = chat_tree.positions(b.node_start, b.node_position, len(b.tokens))
        for node, spans in zip(b.conv_node, (b.attend[n] for n in b.conv_node), strict=True):
            assert [every[k] for x in spans for k in range(x.start, x.end)] == list(range(sum(x.end - x.start for x in spans)))


@pytest.mark.parametrize("sql", ["op2_chat_tree", "op3_exact_dedup"])
def test_query_equals_sql(spark, duck, same, sql):
    same(entries.queries()[sql](spark, DATA), duck.sql(entries.oracle_sql()[sql]))


TEXTS = ["", None, " ", "  Hi\n\nthere  x  é中😀 ", "a" * 200, "\n \n", "x▁y ▁", " " * 11 + "lots", "\t\x00\x7f", "The quick brown fox, 12.5% of it.", "word" * 30]


def test_without_dropout_tokens_are_the_librarys():
    import sentencepiece

    sp, model = sentencepiece.SentencePieceProcessor(model_file=piece_dropout.MODEL), piece_dropout.Model.read()
    rng = random.Random(2)
    texts = TEXTS + ["".join(rng.choice("abc é中😀\n\t thequick") for _ in range(rng.randint(1, 120))) for _ in range(200)]
    flat, n = piece_dropout.encode_texts(pa.array(texts), np.zeros(len(texts), int), model, 0.0)
    for text, tokens in zip(texts, np.split(flat, np.cumsum(n)[:-1]), strict=True):
        if "▁" not in (text or ""):
            assert tokens.tolist() == sp.encode(text or "")


def brute_merge(symbols, unit, model, dropout):
    """Merges one by one: the best pair that is not skipped, leftmost of equals."""
    parts = [(s, i, i + 1) for i, s in enumerate(symbols)]
    while True:
        best = None
        for k in range(len(parts) - 1):
            (a, s, mid), (b, _, e) = parts[k], parts[k + 1]
            made, rank = model.look(np.array([a]), np.array([b]))
            if rank[0] < np.inf and not piece_dropout.skipped(np.array([unit], np.uint64), np.array([s]), np.array([mid]), np.array([e]), dropout)[0] and (best is None or rank[0] < best[0]):
                best = (rank[0], k, int(made[0]))
        if best is None:
            return [p[0] for p in parts]
        k = best[1]
        parts[k : k + 2] = [(best[2], parts[k][1], parts[k + 1][2])]


def test_dropout_forms_agree_vary_and_decode():
    model, rng = piece_dropout.Model.read(), random.Random(3)
    for _ in range(40):
        word = " " + "".join(rng.choice("thequickbrown") for _ in range(rng.randint(1, 20)))
        ids, unit = model.of_char[[ord(c) for c in word]], rng.getrandbits(63)
        want = brute_merge(ids.tolist(), unit, model, 0.3)
        assert piece_dropout.merge_by_agenda(ids.tolist(), unit, model, 0.3)[0] == want
        sym, _, n = piece_dropout.merge_in_step(ids[None], np.array([len(ids)]), np.array([unit], np.uint64), model, 0.3)
        assert sym[0, : n[0]].tolist() == want
    texts = pa.array(TEXTS)
    runs = [piece_dropout.encode_texts(texts, np.full(len(TEXTS), v), model, 0.2) for v in (0, 0, 1)]
    assert np.array_equal(runs[0][0], runs[1][0]) and not np.array_equal(runs[0][0], runs[2][0])
    for flat, n in runs:
        assert [x.decode() for x in piece_dropout.decode_tokens(flat, n, model)] == [t or "" for t in TEXTS]


def test_copies_and_repeated_words_are_cut_anew(spark):
    text = "segmentation of tokenization " * 40
    coded = C.encode(spark, docs(spark, [text] * 3, [7, 7, 7]), "")
    assert len({tuple(r.tokens) for r in coded.collect()}) == 3
    model = piece_dropout.Model.read()
    flat, n = piece_dropout.encode_texts(pa.array([" segmentation" * 200]), np.zeros(1, int), model, 0.1)
    assert piece_dropout.decode_tokens(flat, n, model) == [b" segmentation" * 200]
    pieces, words = [model.text[model.text_at[i] : model.text_at[i + 1]].tobytes() for i in flat], []
    for p in pieces:
        words.append([p]) if p.startswith(b" ") or not words else words[-1].append(p)
    assert len({tuple(w) for w in words}) > 5


def test_sharing_changes_no_tokens(monkeypatch):
    texts, model = pa.array([" ".join(t for t in TEXTS if t) * 5, "unbelievable internationalization of the the the the " * 30]), piece_dropout.Model.read()
    want = piece_dropout.encode_texts(texts, np.array([3, 4]), model, 0.2)
    monkeypatch.setattr(piece_dropout, "SHARED", 0)
    got = piece_dropout.encode_texts(texts, np.array([3, 4]), model, 0.2)
    assert all((a == b).all() for a, b in zip(want, got, strict=True))


def test_what_a_task_keeps_changes_no_tokens():
    model = piece_dropout.Model.read()
    batches = [pa.array([t, "unbelievable internationalization of the the the " * k]) for k, t in enumerate(TEXTS + TEXTS)]
    for dropout in (0.0, 0.2):
        want = [piece_dropout.encode_texts(b, np.array([3, 4]), model, dropout) for b in batches]
        for most in (4_000_000, 40, 0):
            memo = piece_dropout.Memo(3, np.uint8, most), piece_dropout.Memo(1, np.int32, most)
            got = [piece_dropout.encode_texts(b, np.array([3, 4]), model, dropout, memo=memo) for b in batches]
            assert all(np.array_equal(x, y) for w, g in zip(want, got, strict=True) for x, y in zip(w, g, strict=True))


def test_the_hash_table_finds_every_pair_and_no_other():
    model, rng = piece_dropout.Model.read(), np.random.default_rng(4)
    left, right = np.divmod(model.pairs, model.symbols)
    assert np.array_equal(model.place(left, right), np.arange(len(model.pairs)))
    a, b = rng.integers(-1, model.symbols, (2, 100_000))
    known = np.isin(a * model.symbols + b, model.pairs) & (a >= 0) & (b >= 0)
    assert np.array_equal(model.place(a, b) >= 0, known)


def test_tokens_and_text_round_trip(spark):
    df = docs(spark, TEXTS).withColumn("tokens", F.lit("clash"))
    coded = piece_dropout.with_tokens(df)
    assert coded.columns[:2] == ["doc_id", "text"] and dict(coded.dtypes)["tokens"] == "array<int>"
    assert {r.doc_id: r.text for r in piece_dropout.decode(coded).collect()} == {i: t or "" for i, t in enumerate(TEXTS)}
    assert all(r.lossless for r in piece_dropout.report(docs(spark, TEXTS)).collect())
    assert piece_dropout.with_tokens(docs(spark, [])).count() == 0


def test_pages_of_the_table_give_their_article(spark):
    import html

    for r in entries.op7_html_crf(spark, DATA).join(spark.read.parquet(f"{DATA}/pages.parquet").select("page_id", "html"), "page_id").collect():
        inner = re.search(r"<article>(.*?)(</article>|$)", r.html, re.DOTALL)[1]
        want = [" ".join(html.unescape(re.sub("<[^>]*>", "", x.replace("<br>", " "))).split()) for x in re.split("</?(?:p|h1)>", inner)]
        assert r.text == "\n".join(x for x in want if x) and r.n_chars == len(r.text)


def test_field_on_made_pages_and_odd_html(spark):
    model = html_crf.field()
    pages = html_crf.labelled_pages(120, seed=77)
    wrong = sum(a != b for p, y in pages for a, b in zip(model.decode(p), y, strict=True))
    assert wrong <= 0.015 * sum(len(y) for _, y in pages)
    odd = [None, "", "plain words only", "<p>open <b>bold", "<!-- never closed <p>x</p>", "<script>var a='</p>';</script><article><p>One &amp; two.</p></article>", "<a href='x>", "<" * 500, "<div>" * 3000 + "deep", "<table><tr><td>a<td>b</table>"]
    df = spark.createDataFrame([(i, f"u{i}", h) for i, h in enumerate(odd)], "page_id long, url string, html string")
    got = {r.page_id: r.text for r in html_crf.extract(df).collect()}
    assert len(got) == len(odd) and got[0] == got[1] == got[4] == "" and got[5] == "One & two."


def test_pages_that_never_end_are_linear():
    model = html_crf.field()
    began = time.process_time()
    for n, page in ((30_000, "<div>x" * 30_000), (0, "<a " * 50_000), (1, "<a '>" * 40_001 + "x"), (1, '<p "' * 40_001), (0, "</p>" * 40_000), (1, "<a b=" * 40_000 + "'"), (1, "<!-" * 40_000)):
        found = html_crf.blocks(page)
        assert len(found) >= n and len(model.decode(found)) == len(found)
    assert time.process_time() - began < 60


def test_viterbi_finds_the_best_labels():
    rng = np.random.default_rng(1)
    page = html_crf.blocks("<nav><a href=x>Menu</a></nav><article><h1>T</h1><p>Text, and more.</p></article><footer>&copy; x</footer>")
    model = html_crf.Field(rng.normal(size=(len(html_crf.FEATURES), 2)), rng.normal(size=(2, 2)))
    score = [model.emit[f].sum(0) for f in html_crf.active(page)]

    def total(labels):
        return sum(s[y] for s, y in zip(score, labels, strict=True)) + sum(model.step[a, b] for a, b in zip(labels, labels[1:], strict=False))

    every = [[(n >> i) & 1 for i in range(len(page))] for n in range(1 << len(page))]
    assert total(model.decode(page)) == pytest.approx(max(map(total, every)))


KINDS = {"email": r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+", "ip": r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)", "card": r"[0-9]([\x20-]?[0-9])+", "phone": r"\+[0-9][\x20().0-9-]+[0-9]"}


def brute_spans(text):
    out = []
    for kind, pattern in KINDS.items():
        for m in re.finditer(pattern, text):
            digits = re.sub("[^0-9]", "", m[0])
            if kind == "ip" and any(int(x) > 255 for x in m[0].split(".")) or kind == "card" and not (13 <= len(digits) <= 19 and pii_anchors.luhn(digits)) or kind == "phone" and not 9 <= len(digits) <= 15:
                continue
            out.append((kind, *m.span()))
    return out


def test_base_spans_are_the_patterns():
    machine, rng = pii_anchors._automaton(), random.Random(6)
    bits = ["1", "2", "0", "9", ".", "@", "+", "-", " ", "(", ")", "a", "b.c", "x@y.de", "255", "4111 1111 1111 1111", "192.168.0.1", "+49 30 1234567", "%", "_", "é", "\n", "account 12345678", "http://a.b/c?d "]
    for _ in range(8000):
        text = "".join(rng.choice(bits) for _ in range(rng.randint(0, 24)))
        assert [x for x in pii_anchors.spans(text, machine) if x[0] in KINDS] == brute_spans(text)


def test_added_spans_and_edges(spark):
    text = "Konto: DE89370400440532013000, see https://a.example/x?y=1. Account no. 00123-4567"
    got = pii_anchors.spans(text, pii_anchors._automaton())
    assert [text[a:b] for k, a, b in got if k in ("url", "account")] == ["https://a.example/x?y=1", "DE89370400440532013000", "00123-4567"]
    rows = pii_anchors.find(docs(spark, [None, "", "x" * 200_000, text])).collect()
    empty = hashlib.sha256(b"").hexdigest()
    assert [(r.n_email, r.base_sha256, r.spans) for r in rows[:3]] == [(0, empty, "")] * 3
    assert pii_anchors.find(docs(spark, [])).count() == 0


def test_quality_on_held_out_rows(spark):
    sf = DATA.replace("0.001", "0.1")
    labels = spark.read.parquet(f"{sf}/labels.parquet")
    got = quality_qda.score(spark.read.parquet(f"{sf}/documents.parquet"), labels).join(labels, "doc_id").where("held_out").toPandas()
    assert len(got) > 500 and (got.predicted == got.quality).mean() > 0.98 and got.score.between(0, 1).all()


def test_quality_edges(spark):
    d = docs(spark, [None, "", "x", "y z" * 5000])
    none = spark.createDataFrame([], "doc_id long, quality int")
    assert [r.score for r in quality_qda.score(d, none).collect()] == [0.5] * 4
    labels = spark.createDataFrame([(i, i % 2) for i in range(4)] + [(2, None), (99, 1)], "doc_id long, quality int")
    got = quality_qda.score(docs(spark, ["good text here. " * 9] * 40 + ["### $$$ !!! " * 9] * 40), spark.createDataFrame([(i, int(i < 40)) for i in range(80)], "doc_id long, quality int")).collect()
    assert all((r.score > 0.5) == (r.doc_id < 40) for r in got)
    assert quality_qda.score(d, labels).count() == 4 and quality_qda.score(docs(spark, []), labels).count() == 0
    assert quality_qda.accepted(d, none).count() == 4


def test_scores_equal_a_plain_discriminant(spark):
    rng = np.random.default_rng(2)
    texts = [" ".join(rng.choice(["the", "of", "Wort", "data", "###", "!!", "9", "stone,"], int(rng.integers(3, 80)), p=np.array([8, 6, 3, 3, *(4 * [1 + 3 * (i % 2)])]) / (20 + 4 * (1 + 3 * (i % 2))))) for i in range(300)]
    df, labels = docs(spark, texts), spark.createDataFrame([(i, 1 - i % 2) for i in range(0, 300, 1)], "doc_id long, quality int")
    got = {r.doc_id: r for r in quality_qda.score(df, labels).collect()}
    x = quality_qda.statistics_of(pa.array(texts)).astype(np.float32).astype(float)
    learn = np.array([zlib.crc32(str(i).encode()) % 5 != 0 for i in range(300)])
    y = 1 - np.arange(300) % 2
    parts = [x[learn & (y == k)] for k in (0, 1)]
    cov = [np.cov(p.T, bias=True) for p in parts]
    pooled = sum(len(p) * c for p, c in zip(parts, cov, strict=True)) / learn.sum()
    scale = np.diag(np.diag(pooled) + 1e-4)
    pooled = 0.98 * pooled + 0.02 * scale
    density = []
    for p, c in zip(parts, cov, strict=True):
        c = 0.9 * (0.98 * c + 0.02 * scale) + 0.1 * pooled
        d = x - p.mean(0)
        density.append(np.log(len(p)) - 0.5 * np.linalg.slogdet(c)[1] - 0.5 * np.einsum("ij,jk,ik->i", d, np.linalg.inv(c), d))
    want = 1 / (1 + np.exp(-np.clip(density[1] - density[0], -500, 500)))
    assert all(got[i].score == pytest.approx(want[i], abs=1e-6) and got[i].held_out == (not learn[i]) and got[i].predicted == int(got[i].score >= 0.3) for i in range(300))
    kept = {r.doc_id for r in quality_qda.accepted(df.withColumn("l_", F.lit(1)), labels).collect()}
    assert kept == {i for i in range(300) if got[i].predicted}


def test_entropy_classes_are_entropies():
    raw = np.frombuffer(bytes(range(200)) + b"hello world this is a text " * 20 + b"a" * 100, np.uint8)
    for i, c in enumerate(improbable_digest.entropy_classes(raw)):
        n = collections.Counter(raw[i : i + 64].tolist())
        assert abs(c - -sum(v / 64 * math.log2(v / 64) for v in n.values()) * 999 / 6) <= 1.01


def test_fingerprints_of_neighbours(spark):
    rng = random.Random(8)
    texts = [" ".join("".join(rng.choice("abcdefghij") for _ in range(rng.randint(2, 9))) for _ in range(n)) for n in (300, 5, 0, 80, 80, 2000)] + [None, "é" * 90]
    texts[4] = texts[3]
    for parts in (1, 4):
        got = {r.doc_id: r for r in improbable_digest.compare(docs(spark, texts), parts).collect()}
        for i, t in enumerate(texts):
            t, nxt = t or "", texts[(i + 1) % len(texts)] or ""
            want = improbable_digest.edited(t, nxt)
            assert got[i].n_chars == len(t) and got[i].edited_sha256 == hashlib.sha256(want.encode()).hexdigest()
            assert 0 <= got[i].near_edited <= 1 and 0 <= got[i].near_next <= 1
        assert got[3].fingerprint == got[4].fingerprint and got[3].near_next == 1 and got[0].near_edited > 0.3 > got[0].near_next
    assert improbable_digest.compare(docs(spark, [])).count() == 0 and improbable_digest.compare(docs(spark, ["x"])).first().near_next == 1
    repeated = docs(spark, ["a b c", "a b d", None], [1, 1, None])
    assert improbable_digest.compare(repeated, 3).count() == 3


def brute_digest(text, rarity):
    """The same window by window, with sets and loops."""
    d = improbable_digest
    starts, n = [], len(text) - d.WINDOW + 1
    if n > 0:
        classes = d.entropy_classes(np.frombuffer(text, np.uint8)).tolist()
        votes = collections.Counter()
        width = min(d.NEIGHBOURS, n)
        for k in range(n - width + 1):
            votes[min(range(k, k + width), key=lambda i: (rarity[classes[i]], i))] += 1
        starts = [i for i in range(n) if votes[i] >= min(d.POPULAR, n - width + 1)]
    h = list(dict.fromkeys(xxhash.xxh64_intdigest(text[i : i + d.WINDOW], 7) for i in starts))
    if len(h) < d.FEW:
        small = [int.from_bytes(text[i : i + 8], "little") for i in range(len(text) - 7)] if len(text) >= 8 else [xxhash.xxh64_intdigest(text, 7)]
        h += [int(x) for x in mixed(np.array([(x + 7) % 2**64 for x in dict.fromkeys(small)], np.uint64))]
    filters = [{(x >> 11 * k) & 2047 for x in h[i : i + d.PER_FILTER] for k in range(d.HASHES)} for i in range(0, len(h), d.PER_FILTER)]
    return filters, [len(h[i : i + d.PER_FILTER]) for i in range(0, len(h), d.PER_FILTER)]


def brute_likeness(a, b):
    if a == b:
        return 1.0
    total, bits = 0.0, improbable_digest.BLOOM_BYTES * 8
    for x in a[0]:
        best = 0.0
        for y in b[0]:
            chance = len(x) * len(y) / bits
            low, most = chance + 0.05 * (min(len(x), len(y)) - chance), min(len(x), len(y))
            best = max(best, min(1.0, max(0.0, (len(x & y) - low) / max(most - low, 1e-9))))
        total += best
    return total / len(a[0])


def test_digests_equal_brute_force(spark):
    rng = random.Random(12)
    texts = ["".join(rng.choice("abcdefgh ijk,.") for _ in range(n)) for n in (0, 3, 7, 8, 63, 64, 65, 130, 700, 9000)] + ["ab" * 300]
    ranks = improbable_digest.fit_rarity(docs(spark, texts))
    windows = collections.Counter(c for t in texts if len(t) >= 64 for c in improbable_digest.entropy_classes(np.frombuffer(t.encode(), np.uint8)).tolist())
    order = sorted(range(improbable_digest.CLASSES), key=lambda c: (windows[c], c))
    assert [order.index(c) for c in windows] == [ranks[c] for c in windows]
    got = improbable_digest.digests([t.encode() for t in texts], ranks)
    want = [brute_digest(t.encode(), ranks) for t in texts]
    for (blob, counts), (filters, sizes) in zip(got, want, strict=True):
        bits = np.unpackbits(np.frombuffer(blob, np.uint8)).reshape(len(counts), -1)
        assert counts == sizes and [set(np.flatnonzero(b).tolist()) for b in bits] == filters
    for i in range(len(texts)):
        for j in range(len(texts)):
            if len(want[i][0]) < len(want[j][0]):
                assert improbable_digest.likeness(got[i], got[j]) == pytest.approx(brute_likeness(want[i], want[j]))


def test_targets_fill_up_to_their_caps():
    t = pareto_mix.targets([("a", 10), ("b", 1000), (None, 100)])
    assert t["a"] == 30 and sum(t.values()) == pytest.approx(1110) and t[None] <= 300
    assert pareto_mix.targets([]) == {} and pareto_mix.targets([("a", 0)]) == {"a": 0}


def brute_mix(rows, u, most=3.0):
    """(words taken, rows that lie next to a stratum's cut) by sorting: ``rows`` of (doc_id, size, source)."""
    goal = pareto_mix.targets([(s, sum(n for _, n, t in rows if t == s)) for s in {s for _, _, s in rows}])
    taken = {}
    for s, target in goal.items():
        mine = [(i, n) for i, n, t in rows if t == s and n]
        grades = {i: math.floor(round(math.log2(n) * 8, 9)) for i, n in mine}
        worth = lambda c: {i: min(most, c * 2 ** (0.25 * grades[i] / 8)) for i, _ in mine}  # noqa: E731, B023
        low, high = 0.0, 100.0
        for _ in range(200):
            mid = (low + high) / 2
            low, high = (mid, high) if sum(worth(mid)[i] * n for i, n in mine) < target else (low, mid)
        w = worth(high)
        whole = {i: math.floor(round(v, 9)) for i, v in w.items()}
        p = {i: max(0.0, w[i] - whole[i]) for i in w}
        key = {i: (u[i] / (1 - u[i])) / (p[i] / (1 - p[i])) for i, _ in mine if p[i] > 1e-9}
        for octave in {g // 8 for g in grades.values()}:
            line = sorted((key[i], i, n) for i, n in mine if i in key and grades[i] // 8 == octave)
            left = sum(n * p[i] for _, i, n in line)
            for _, i, n in line:
                taken[i] = n * (whole[i] + (left >= n / 2))
                left -= n
        taken |= {i: n * whole[i] for i, n in mine if i not in key}
    return taken


def test_mix_ranks_by_odds_as_brute_force_does(spark):
    rng = np.random.default_rng(9)
    rows = [(i, int(n), f"s{s}") for i, (n, s) in enumerate(zip(rng.integers(1, 400, 900), rng.integers(0, 5, 900), strict=True))]
    df = spark.createDataFrame([(i, "w " * n, "en", s, 0) for i, n, s in rows], "doc_id long, text string, lang string, source string, n_chars long")
    u = {r.doc_id: r.u for r in df.select("doc_id", pareto_mix.uniform().alias("u")).collect()}
    want, got = brute_mix(rows, u), {r.doc_id: r.taken for r in pareto_mix.mix(df).collect()}
    # The correction pass moves a few small documents of each source.
    moved = [i for i, _, _ in rows if want.get(i, 0) != got[i]]
    assert len(moved) <= 0.02 * len(rows)
    copies = collections.defaultdict(list)
    for i, n, s in rows:
        copies[s, n > 100].append(got[i] / n)
    assert sum(np.mean(copies[f"s{k}", True]) > np.mean(copies[f"s{k}", False]) for k in range(5)) >= 4


def test_repeated_rows_and_clashing_names_in_the_mix(spark):
    df = docs(spark, ["a b c", "a b c", "x " * 50, None, "y " * 9], [1, 1, 1, 1, 2]).selectExpr("*", "'c' AS copies", "1 AS row", "2 AS id", "3 AS of", "4 AS time")
    taken = pareto_mix.mix(df).toPandas()
    picked = pareto_mix.pick(df, column="times")
    assert picked.columns == [*df.columns, "times"] and picked.where("copies <> 'c'").count() == 0
    words = picked.select("*", pareto_mix.word_count(F.col("text")).alias("n")).toPandas()
    assert (words.n * words.times).sum() == taken.taken.sum()
    again = C.mix(spark, df, "")
    assert again.columns == df.columns and again.count() == words.times.sum()
    assert C.exact(spark, df.selectExpr("*", "1 AS sha_", "2 AS id_", "3 AS again", "4 AS sha"), "").count() == 4


def test_mix_meets_targets(spark):
    rng = np.random.default_rng(4)
    rows = [(i, "w " * int(n), "en", None if s == 5 else f"s{s}", 0) for i, (n, s) in enumerate(zip(rng.integers(0, 300, 1500), np.minimum(rng.integers(0, 12, 1500), 6), strict=True))]
    rows += [(2000, None, "en", "s0", 0), (None, "a b", "en", "s1", 0)]
    df = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long")
    got = pareto_mix.mix(df).toPandas()
    again = pareto_mix.mix(df.repartition(5)).toPandas()
    assert len(got) == len(rows) and (got.taken <= 3 * got["size"]).all()
    assert got.sort_values(["doc_id", "size"]).taken.tolist() == again.sort_values(["doc_id", "size"]).taken.tolist()
    for _, g in got.groupby("source", dropna=False):
        assert abs(g.taken.sum() - g.target.iloc[0]) <= 0.02 * g.target.iloc[0]
    assert pareto_mix.mix(docs(spark, [])).count() == 0
