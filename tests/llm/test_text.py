"""WARC, media, quality, pieces, HTML, packing, language model and the pipeline on small cases."""

import base64
import hashlib
import math
import re
import zlib
from collections import Counter

import numpy as np

from optjoin.llm import html_text, jpeg, lm, packing, pieces, quality, warc

DOCS = [(1, "alpha beta gamma " * 40), (2, None), (3, ""), (4, "Ünï 中文 😀 <|endoftext|>  two  spaces\n\nlines"), (4, "x"), (None, "null id"), (7, "alpha beta gamma " * 40), (8, "the of and a b c d e f g h i j k l m n o p q r s t")]


def frame(spark, rows=DOCS):
    return spark.createDataFrame(rows, "doc_id long, text string")


def test_warc(spark, tmp_path):
    pages = [(5, "http://a/ b", "<p>one"), (2, None, "<p>one"), (9, "http://c", None), (11, "http://d", ""), (3, "u", "two"), (3, "u", "two"), (None, "n", "three")]
    folder = f"file://{tmp_path}/archive"
    manifest = warc.write_warc(spark.createDataFrame(pages, "page_id long, url string, html string"), folder, roll_bytes=600)
    got = sorted(((r.page_id, r.payload_bytes, r.payload_digest, r.record_type, r.refers_to, bytes(r.payload)) for r in warc.read_warc(manifest, folder, payloads=True).collect()), key=str)
    digest = lambda t: base64.b32encode(hashlib.sha1((t or "").encode()).digest()).decode()
    want = []
    for i, _, t in pages:
        same = [j for j, _, u in pages if (u or "") == (t or "") and j is not None]
        first = min(same) if same and (i is None or min(same) < i) else None
        want.append((i, len((t or "").encode()), digest(t), "response" if first is None else "revisit", first, (t or "").encode() if first is None else b""))
    assert got == sorted(want, key=str)
    assert manifest.count() > 1


def test_media_round_trip(spark):
    draw = np.random.default_rng(0)
    payloads = [b"", b"a", bytes([128] * 500), draw.integers(0, 256, 1000, dtype=np.uint8).tobytes(), b"\xff" * 400, b"hello" * 9000]
    files = jpeg.encode_all(np.frombuffer(b"".join(payloads), np.uint8), [len(p) for p in payloads])
    for p, (image, found) in zip(payloads, jpeg.decode(files), strict=True):
        n, mcus = (int.from_bytes(image.comments[0][i : i + 8], "big") for i in (0, 8))
        stored = (found[:mcus].reshape(-1) + 128).astype(np.uint8).tobytes()
        assert stored[:n] == p and set(stored[n:]) <= {32} and len(stored) % 192 == 0 and len(stored) > 0
        assert jpeg.thumbnail(image, found).shape == (image.height // 8, image.width // 8)
    rows = jpeg.media_columns(frame(spark)).collect()
    for r, (d, t) in zip(sorted(rows, key=str), sorted(rows, key=str) and DOCS, strict=False):
        assert r.payload_bytes % 192 == 0
    by_id = {r.doc_id: r for r in rows}
    assert by_id[1].media_sha256 == by_id[7].media_sha256 and by_id[1].feature == by_id[7].feature
    padded = DOCS[0][1].encode().ljust(-(-len(DOCS[0][1]) // 192) * 192)
    assert by_id[1].payload_sha256 == hashlib.sha256(padded).hexdigest() and by_id[1].tail_crc32 == zlib.crc32(padded[-16:])


def test_quality(spark):
    rows = DOCS + [(20, "a b c d e f g h\n" * 4 + "tail $ # | x"), (21, ("w%d " * 30) % tuple(range(30)))]
    got = {r.doc_id: r for r in quality.quality(frame(spark, [x for x in rows if x[0] not in (None, 4)])).collect()}
    for d, t in rows:
        if d in (None, 4):
            continue
        w = re.findall(r"[^\x20\x09-\x0D]+", t or "")
        seen = Counter(tuple(w[i : i + 8]) for i in range(len(w) - 7))
        mark = [0] * len(w)
        for i in range(len(w) - 7):
            if seen[tuple(w[i : i + 8])] > 1:
                mark[i : i + 8] = [1] * 8
        lines = [x for x in (t or "").split("\n") if re.search(r"[^\x20\x09-\x0D]", x)]
        r = got[d]
        assert (r.n_words, r.word_chars, r.n_symbols, r.n_dup_lines, r.n_repeat_words) == (len(w), sum(map(len, w)), len(re.findall(r"[#*$%&|<>]", t or "")), len(lines) - len(set(lines)), sum(mark))
        assert r.base_failed == (len(w) < 20 or 100 * sum(mark) > 30 * len(w))


def test_pieces(spark):
    model = pieces.public_piece_model()
    score = {model.pieces[i]: s for piece, (n, s, i) in model.automaton.items()}
    for text in ("the cat sat on the mat", "  two  spaces ", "中文ab😀", "Ünï"):
        marked = "▁" + text.replace(" ", "▁")
        best = [0.0]
        for end in range(1, len(marked) + 1):
            options = [best[s] + score[marked[s:end]] for s in range(end) if marked[s:end] in score]
            best.append(max(options + ([] if marked[end - 1] in score else [best[end - 1] + model.unknown])))
        ids = model.encode(text).tolist()
        assert model.decode(ids) == text
        if all(ord(c) < 0x250 for c in text):
            assert math.isclose(sum(score[model.pieces[i]] for i in ids), best[-1])
    rows = pieces.encode_documents(frame(spark)).collect()
    assert len(rows) == len(DOCS)
    assert {r.decoded_sha256 for r in rows} == {hashlib.sha256((t or "").encode()).hexdigest() for _, t in DOCS}


def test_html():
    page = "<title>no</title><p>One<p>Two <b>bold</b>,x<br>y<ul><li>a<li>b<ol><li>c<li>d</ol></ul><table><tr><th>Name<th>Qty<tr><td>apple<td>3</table><div hidden>no</div><span style='display: none'>no</span>end<script>no</script>&amp;"
    assert html_text.extract(page) == "One\n\nTwo bold,x\ny\n\n- a\n- b\n  1. c\n  2. d\n\nName   Qty\napple  3\n\nend&"
    assert html_text.extract(None) == html_text.extract("<!--") == ""
    assert html_text.extract("<div " * 3000 + "x") != "y"
    assert "deep" in html_text.extract("<div>" * 5000 + "deep")


def test_packing(spark):
    from tokenizers import Tokenizer

    import public_tokenizers

    coder = Tokenizer.from_file(public_tokenizers.path("byte_bpe_50k.json"))
    coder.encode_special_tokens = True
    rows = [x for x in DOCS if x[0] not in (4, None)] + [(50, "long text here " * 3000), (51, "  lead and  double \n x")]
    ids = {d: np.array([*coder.encode(t or "", add_special_tokens=False).ids, 1], "<u4") for d, t in rows}
    held, placed = Counter(), {}
    for r in packing.pack(frame(spark, rows)).collect():
        assert r.doc_tokens == len(ids[r.doc_id]) and r.ids_crc32 == zlib.crc32(ids[r.doc_id][r.start : r.start + r.length])
        held[r.doc_id] += r.length
        placed.setdefault(r.sequence_id, []).append((r.offset, r.length))
    assert held == Counter({d: len(x) for d, x in ids.items()})
    for parts in placed.values():
        at = 0
        for offset, length in sorted(parts):
            assert offset == at
            at += length
        assert at <= 2048


def test_language_model(spark):
    rows = [(1, "a b c a b"), (2, "a b d"), (3, None), (4, "c a b c")]
    words = {d: (t or "").split() for d, t in rows}
    got = {r.doc_id: r.log_score for r in lm.score_documents(frame(spark, rows), order=3, shard_bytes=8).collect()}
    for d, w in words.items():
        grams = Counter()
        for e, x in words.items():
            if e != d:
                grams.update(tuple(x[i : i + n]) for n in range(4) for i in range(len(x) - n + 1) if n or i < len(x))
        total = 0.0
        for i in range(len(w)):
            s = max(grams[(w[i],)], 0.5) / max(grams[()], 1)
            for n in (2, 3):
                if i + 1 >= n:
                    g = tuple(w[i - n + 1 : i + 1])
                    s = grams[g] / grams[g[:-1]] if grams[g] else 0.4 * s
            total += math.log(s)
        assert math.isclose(got[d], total, abs_tol=1e-9)


def test_pipeline_stages(spark):
    import corpus_pipeline as cp

    base = "the of and " + " ".join(f"word{i}" for i in range(120))
    near = base.replace("word60", "other")
    rows = [(1, base), (2, base), (3, near), (4, "short"), (5, "the of and " + " ".join(f"term{i}" for i in range(90)) + " " + " ".join(f"word{i}" for i in range(30))), (6, None)]
    docs = spark.createDataFrame([(d, t, "en", "s", len(t or "")) for d, t in rows], "doc_id long, text string, lang string, source string, n_chars long")
    kept = cp.quality_rules(spark, docs, "")
    assert {r.doc_id for r in kept.collect()} == {1, 2, 3, 5}
    single = cp.near_duplicates(spark, kept, "")
    assert {r.doc_id for r in single.collect()} == {1, 5}
    cut = {r.doc_id: r.text for r in cp.repeated_substrings(spark, single, "").collect()}
    assert cut[1] == base and "word15" not in cut[5] and "term80" in cut[5]
    assert cp.packing(spark, cp.repeated_substrings(spark, single, ""), "").count() >= 2


def test_warc_is_deterministic(spark, tmp_path):
    rows = [(i, f"http://x/{i}", f"<p>{i % 40}" * (1 + i % 90)) for i in range(600)] + [(7, "http://x/7", "<p>7" * 8), (7, "http://x/7", "<p>7" * 8), (None, None, None), (None, None, "x")]
    found = []
    for run, parts in enumerate((1, 5)):
        folder = f"file://{tmp_path}/warc{run}"
        pages = spark.createDataFrame(rows[run::2] + rows[1 - run :: 2], "page_id long, url string, html string").repartition(parts)
        manifest = warc.write_warc(pages, folder, roll_bytes=4000, range_bytes=20_000)
        found.append(sorted((r.file, r.records, r.sha1) for r in manifest.collect()))
        back = warc.read_warc(manifest, folder)
        assert back.count() == len(rows) and back.rdd.getNumPartitions() == len(found[-1])
        ids = []
        for path in sorted((tmp_path / f"warc{run}").glob("*.warc.gz")):
            with path.open("rb") as file:
                ids += [f["WARC-Record-ID"] for f, _ in warc.parse_records(file.read)]
        assert len(ids) == len(set(ids)) == len(rows)
    assert found[0] == found[1] and len({f[0][:6] for f in found[0]}) > 3
    empty = spark.createDataFrame([], "page_id long, url string, html string")
    assert warc.write_warc(empty, f"file://{tmp_path}/none").count() == 0


def test_rowspan():
    page = "<table><tr><td rowspan=2>A<td>b<tr><td>c</table>"
    assert html_text.extract(page) == "A  b\n   c"
    page = "<table><tr><td>1<td rowspan=0 colspan=2>wide<td>x<tr><td>2<td>y<tr><td>3<td>z</table>"
    assert html_text.extract(page) == "1  wide  x\n2        y\n3        z"
