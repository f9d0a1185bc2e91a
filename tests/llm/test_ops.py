"""Each operator against a brute-force version, with nulls, empty and long texts, ties, repeated rows and clashing columns."""

import hashlib
import random
import re
import zlib

import numpy as np
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

from pathsieve.llm import compaction, decontaminate, language_id, licenses, line_dedup, near_dedup, quality_mil, quality_rules, sentence_pieces, token_shards

public_tokenizers = pytest.importorskip("public_tokenizers")
PIECES, WORDS = public_tokenizers.path("piece_bpe_32k.model"), public_tokenizers.path("word_bpe_49k.json")
COLUMNS = "doc_id long, text string, lang string, source string, n_chars long, n_words long, kept boolean"


def words(n, seed, kinds=400):
    rng = random.Random(seed)
    return " ".join(f"w{rng.randrange(kinds)}" for _ in range(n))


def table(spark, texts):
    return spark.createDataFrame([(i, t, "en", "s", len(t or ""), -1, None) for i, t in enumerate(texts)], COLUMNS)


@pytest.fixture(scope="module")
def texts():
    base = words(120, 1)
    near = base.split()
    near[60] = "changed"
    return [base, base, " ".join(near), base.upper(), None, "", "  \n\t ", "one", "One", "one two three", words(3000, 2, 9000), words(80, 3) + " " + base, "é中\U0001f600 x", "a " * 300, words(60, 4) + "\n" + words(60, 5)]


def test_line_dedup(spark):
    long = "\n".join([words(30, 1), words(30, 2)])
    rows = [long, "start\n" + long + "\n\nend", words(30, 1) + "\nother", None, "", "short\nshort", words(60, 9), words(60, 9), long + "\n" + long]
    out = {r.doc_id: r for r in line_dedup.without_repeated_lines(table(spark, rows)).collect()}
    assert out[0].text == long and out[1].text == "start\n\nend" and out[2].text == rows[2]
    assert out[3].text is None and out[4].text == "" and out[5].text == "short\nshort" and out[6].text == rows[6] and out[7].text == ""
    assert out[8].text == "" and out[1].n_chars == len("start\n\nend") and out[6].n_chars == len(rows[6])
    again = line_dedup.without_repeated_lines(table(spark, [out[k].text for k in sorted(out)]))
    assert {r.n_removed for r in again.collect()} == {0}
    assert line_dedup.without_repeated_lines(table(spark, [long]).limit(0)).count() == 0


@pytest.mark.parametrize("seed", range(3))
def test_line_dedup_guarantee(spark, seed):
    """No run of lines with WINDOW_WORDS words that stood in an earlier text is left whole."""
    rng = random.Random(seed)
    pool = [words(rng.randint(3, 40), 100 + i) for i in range(25)]
    docs = ["\n".join(rng.choices(pool, k=rng.randint(1, 14))) for _ in range(40)]
    got = {r.doc_id: r.text for r in line_dedup.without_repeated_lines(table(spark, docs)).collect()}
    seen = set()
    for i, text in enumerate(docs):
        lines, kept = text.split("\n"), got[i].split("\n")

        def runs(ls):
            for a in range(len(ls)):
                n = 0
                for b in range(a, len(ls)):
                    n += len(ls[b].split())
                    if n >= line_dedup.WINDOW_WORDS:
                        yield tuple(ls[a : b + 1])
                        break

        for r in runs(lines):
            assert r not in seen or not any(tuple(kept[a : a + len(r)]) == r for a in range(len(kept)))
        seen |= set(runs(lines))


def repeated_run_lines(docs, least):
    """For each text, the lines of all runs with ``least`` words or more that also stand earlier, by brute force."""
    split, seen, out = [d.split("\n") for d in docs], set(), []
    for ls in split:
        gone = set()
        runs = [(a, b) for b in range(1, len(ls) + 1) for a in range(b) if sum(len(x.split()) for x in ls[a:b]) >= least]
        for a, b in sorted(runs):
            key = tuple(ls[a:b])
            if key in seen:
                gone |= set(range(a, b))
            seen.add(key)
        out.append(gone)
    return out


def test_line_dedup_hot_line_inside_passage(spark):
    """A line of 30 words that stood first in other texts hides no line of the passages around it."""
    hot, docs = words(30, 1), [f"own {words(20, 50 + i)}\n{words(30, 1)}\n{words(20, 80 + i)} end" for i in range(20)]
    for i in range(20):
        passage = "\n".join([words(20, 200 + i), hot, words(20, 300 + i)])
        docs += [f"{words(20, 400 + 2 * i + j)}\n{passage}\n{words(20, 500 + 2 * i + j)}" for j in range(2)]
    out = {r.doc_id: r for r in line_dedup.without_repeated_lines(table(spark, docs)).collect()}
    for i in range(20, 60, 2):
        assert out[i + 1].text == docs[i + 1].split("\n")[0] + "\n" + docs[i + 1].split("\n")[4] and out[i + 1].n_removed == 3


@pytest.mark.parametrize("seed", range(3))
def test_line_dedup_removes_whole_runs(spark, seed):
    rng = random.Random(seed)
    pool = [words(rng.choice([3, 5, 12, 24, 30, 49, 50, 60]), 100 + i) for i in range(25)]
    docs = ["\n".join(rng.choices(pool, k=rng.randint(1, 14))) for _ in range(40)]
    texts = [docs[i] + f"\n{'own ' * 3}{i}" for i in range(len(docs))]
    got = {r.doc_id: r for r in line_dedup.repeated_lines(table(spark, texts)).selectExpr("CAST(split(row_key, ':')[1] AS long) AS doc_id", "lines").collect()}
    removed = [set(got[i].lines if i in got else ()) for i in range(len(docs))]
    for must, may, gone in zip(repeated_run_lines(texts, line_dedup.WINDOW_WORDS), repeated_run_lines(texts, line_dedup.GRAM_WORDS), removed, strict=True):
        assert must <= gone <= may


def test_line_dedup_of_passages_that_begin_elsewhere(spark):
    """A gram first seen in another text than the passage around it: every line of the later passage goes, and nothing else."""
    docs = []
    for i in range(60):
        x, g, y = (("\n".join(words(n, 1000 * i + k + j) for j, n in enumerate(ns))) for k, ns in ((0, (5, 4, 6)), (100, (5, 6, 4, 5, 5)), (200, (6, 5, 4))))
        own = [words(9, 1000 * i + 300 + j, 9000) for j in range(4)]
        docs += [f"{own[0]}\n{g}\n{own[1]}", f"{x}\n{g}\n{y}", f"{own[2]}\n{x}\n{g}\n{y}\n{own[3]}"]
    got = {r.doc_id: r.text for r in line_dedup.without_repeated_lines(table(spark, docs)).collect()}
    for i in range(60):
        lines = docs[3 * i + 2].split("\n")
        assert got[3 * i] == docs[3 * i] and got[3 * i + 2] == lines[0] + "\n" + lines[-1]


def test_ids_that_are_strings(spark):
    docs = table(spark, [words(60, 1), words(60, 1), None]).withColumn("doc_id", F.concat(F.lit("document-with-a-long-name-"), "doc_id"))
    out = {r.doc_id[-1]: r for r in line_dedup.without_repeated_lines(docs).collect()}
    assert out["0"].n_removed == 0 and out["1"].text == "" and out["2"].text is None
    left = line_dedup.without_repeated_lines(docs, emptied=False)
    assert {r.doc_id[-1] for r in left.collect()} == {"0", "2"}
    assert {r.doc_id[-1]: r.n_tokens for r in token_shards.token_shards(docs, WORDS).collect()}["2"] == 1
    assert near_dedup.without_near_duplicates(docs).count() == 2


def test_sentence_pieces(spark, texts):
    import sentencepiece

    sp = sentencepiece.SentencePieceProcessor(model_file=PIECES)
    rng = random.Random(5)
    rows = texts + ["".join(rng.choice("abetio n.\n é'A1中\x00") for _ in range(rng.randint(1, 50))) for _ in range(200)] + ["aaaaaaaaa", " " * 40, "▁ x"]
    got = {r.doc_id: r for r in sentence_pieces.encode(table(spark, rows), PIECES).collect()}
    for i, t in enumerate(rows):
        assert got[i].ids == (sp.encode(t) if t else []) and got[i].n_pieces == len(got[i].ids)
        assert got[i].round_trip == ("▁" not in (t or ""))
    back = {r.doc_id: r.text for r in sentence_pieces.decode(sentence_pieces.encode(table(spark, rows), PIECES), PIECES).collect()}
    assert all(back[i] == (t or "").replace("▁", " ") for i, t in enumerate(rows))


def _field(number, value):
    """One field of a protocol buffer message."""
    import struct

    def varint(n):
        out = b""
        while n > 127:
            out, n = out + bytes([n & 127 | 128]), n >> 7
        return out + bytes([n])

    if isinstance(value, float):
        return varint(number << 3 | 5) + struct.pack("<f", value)
    if isinstance(value, int):
        return varint(number << 3) + varint(value)
    return varint(number << 3 | 2) + varint(len(value)) + value


def unigram_file(path, byte_pieces, seed):
    """A model file written field by field: pieces of random scores, no training."""
    rng = random.Random(seed)
    pieces = [("<unk>", 0.0, 2), ("<s>", 0.0, 3), ("</s>", 0.0, 3)] + ([(f"<0x{i:02X}>", 0.0, 6) for i in range(256)] if byte_pieces else [])
    texts = {"▁", *"abcdei"} | {("▁" if rng.random() < 0.4 else "") + "".join(rng.choices("abcdei", k=rng.randint(1, 4))) for _ in range(120)} | {"▁▁", "é"}
    pieces += [(t, -rng.randint(8, 96) / 8, 1) for t in sorted(texts)]  # sums are exact in any precision, so equal sums are ties everywhere
    proto = b"".join(_field(1, _field(1, t.encode()) + _field(2, x) + _field(3, kind)) for t, x, kind in pieces)
    proto += _field(2, _field(3, 1) + (_field(35, 1) if byte_pieces else b"")) + _field(3, _field(1, b"identity") + _field(3, 1) + _field(4, 0) + _field(5, 1))
    path.write_bytes(proto)
    return str(path)


@pytest.mark.parametrize("byte_pieces", [True, False])
def test_sentence_pieces_of_a_unigram_model(tmp_path, byte_pieces):
    """Shared-prefix Viterbi against the library, and its scores against all segmentations."""
    import sentencepiece

    path = unigram_file(tmp_path / "unigram.model", byte_pieces, 4)
    sp, rng = sentencepiece.SentencePieceProcessor(model_file=path), random.Random(6)
    rows = ["".join(rng.choice("abcdei  é中z") for _ in range(rng.randint(1, 40))) for _ in range(400)] + ["", "zzz中", "   a", "a   "]
    for i, j, ids, at, back in sentence_pieces.encode_rows(pa.array(rows), path):
        got = [ids[s:e].tolist() for s, e in zip(at[:-1], at[1:], strict=True)]
        assert (i, j) == (0, len(rows)) and got == [sp.encode(t) for t in rows]
        if byte_pieces:
            assert back.all()
    m = sentence_pieces.model(path)

    def best(word):
        return max((m.score[word[:k]] + best(word[k:]) for k in range(1, len(word) + 1) if word[:k] in m.vocab), default=0.0 if not word else -1e9)

    for word in (" abcde", " cab", " deadbe"):
        (found,) = m.best_words([word.encode()])
        assert sum(m.score[m.text[x]] for x in found) == pytest.approx(best(word.replace(" ", "▁")))


def test_sentence_pieces_refuse_other_models(tmp_path):
    piece = _field(1, _field(1, b"<unk>") + _field(3, 2)) + _field(1, _field(1, "▁a".encode()) + _field(2, -1.0))
    (tmp_path / "word.model").write_bytes(piece + _field(2, _field(3, 3)) + _field(3, _field(4, 0)))
    (tmp_path / "trims.model").write_bytes(piece + _field(2, _field(3, 1)) + _field(3, _field(4, 1)))
    for name in ("word", "trims"):
        with pytest.raises(ValueError):
            sentence_pieces.PieceModel(str(tmp_path / f"{name}.model"))


@pytest.mark.parametrize("bound", [1 << 20, 0])
def test_decontamination(spark, bound):
    items = {1: words(30, 1), 2: "Short One", 3: None, 4: "", 5: words(30, 1), 6: words(12, 8), 10: "x"}
    docs = [words(40, 7) + " " + words(30, 1).upper() + " tail", "a short, one! b", None, "", words(500, 9), words(9, 8), words(12, 8) + " " + words(12, 8), " ".join(words(30, 1).split()[5:16]), "short", "x x x"]
    bench = spark.createDataFrame([(k, v, 0) for k, v in items.items()], "item_id long, text string, n_hit int")
    got = {r.doc_id: (r.n_words, r.n_hit, r.n_items, r.items_sha256) for r in decontaminate.contamination(table(spark, docs), bench, broadcast_bytes=bound).collect()}
    want = decontaminate.brute_force(docs, {k: v for k, v in items.items() if v})
    assert [got[i] for i in range(len(docs))] == want
    assert decontaminate.without_contaminated(table(spark, docs), bench).columns == COLUMNS.replace(" long", "").replace(" string", "").replace(" boolean", "").split(", ")
    assert decontaminate.contamination(table(spark, docs), bench.limit(0), broadcast_bytes=bound).where("contaminated").count() == 0


def test_token_shards(spark, texts):
    from tokenizers import Tokenizer

    t = Tokenizer.from_file(WORDS)
    rows = texts + ["İΣ ΑΣ don't we'll x", "#hash ... 123"]
    got = sorted(token_shards.token_shards(table(spark, rows).repartition(3), WORDS).collect(), key=lambda r: r.doc_id)
    at = 0
    for r, text in zip(got, rows, strict=True):
        ids = t.encode(text or "", add_special_tokens=False).ids + [2]
        assert (r.start, r.n_tokens, r.ids_crc32) == (at, len(ids), zlib.crc32(np.array(ids, "<u4").tobytes()))
        at += len(ids)
    assert token_shards.token_shards(table(spark, rows).limit(0), WORDS).count() == 0


def test_shard_format():
    docs = [np.arange(n, dtype="<u4").tobytes() for n in (0, 5, 1000)]
    key = token_shards.train_dictionary([np.arange(i, i + 300, dtype="<u4").tobytes() for i in range(200)], 4096)
    image = token_shards.pack(docs, key)
    r = token_shards.ShardReader(image, key)
    assert [r.raw(k) for k in (2, 0, 1)] == [docs[2], docs[0], docs[1]]
    with pytest.raises(ValueError):
        token_shards.ShardReader(image, b"other")
    with pytest.raises(ValueError):
        token_shards.ShardReader(b"x" * 200, key)


def test_license_scan(spark, texts):
    long = licenses.TEMPLATES[0][1]
    part = long.split()
    rows = [words(50, 1) + "\nReleased under the MIT License.\n" + words(50, 2), words(300, 3) + " " + long.upper(), " ".join(part[: len(part) // 2]), "Licensed under CC BY-NC 4.0.", *texts]
    got = {r.doc_id: (r.licenses, set(r.templates)) for r in licenses.license_scan(table(spark, rows)).collect()}
    assert got[0][0] == ["MIT"] and got[1][0] == ["MIT"] and got[2][0] == [] and got[3][0] == ["CC-BY-NC-4.0"]
    p = licenses.plan()
    for i, t in enumerate(rows):
        ((_, _, h, rows_at),) = licenses._shingled(pa.array([t or ""]), 5)
        want = set()
        for layer in p.layers:
            for s in range(0, len(h), layer.step):
                part_ = set(h[s : s + layer.step * layer.steps].tolist())
                near = {x for x in layer.templates if 100 * len(part_ & set(p.sets[x].tolist())) >= 80 * len(p.sets[x])}
                want |= {x for x in near if all(part_ & set(t.tolist()) for t in p.tells[x])}
        assert got[i][1] == want
    for y in p.layers:
        small, window = min(len(p.sets[t]) for t in y.templates), y.step * y.steps
        held = -(-small * 80 // 100)
        assert (1 - held / (window + small - held)) ** y.bands <= 1.01e-6


def test_license_notices_that_differ_in_a_version(spark):
    """Of licenses whose notices are nearly the same, only the one named is found."""
    notices = [(name, text) for name, text in licenses.TEMPLATES]
    texts = [f"{words(30, 1)}\n{text}\n{words(30, 2)}" for _, text in notices]
    texts += ["This work is licensed under the GNU General Public License, version 2.", "distributed under the MIT license", "This work is licensed under a Creative Commons Attribution 4.0 International License.", "Licensed under the GNU General Public License, version 9 and no other"]
    got = {r.doc_id: r.licenses for r in licenses.license_scan(table(spark, texts)).collect()}
    want = [[name] for name, _ in notices] + [["GPL-2.0"], ["MIT"], ["CC-BY-4.0"], []]
    assert [got[i] for i in range(len(texts))] == want


def _rules_by_hand(text):
    w = [x for x in re.split(r"[\x20\x09-\x0D]+", text or "") if x]
    grams = [tuple(w[i : i + 3]) for i in range(len(w) - 2)]
    twice = {g for g in grams if grams.count(g) > 1}
    covered = {i + j for i, g in enumerate(grams) if g in twice for j in range(3)}
    lines = [x for x in (text or "").split("\n") if re.search(r"[^\x20\x09-\x0D]", x)]
    return len(w), sum(map(len, w)), len(re.findall(r"[#*$%&|<>]", text or "")), len(lines) - len(set(lines)), len(covered)


def test_quality_rules(spark, texts):
    rows = [*(t for t in texts if not t or len(t) < 5000), "a b c a b c a b", "x\ny\nx\n \n ", "| | " * 40, "the and of " * 3 + words(60, 2), "\x0bé ü\x0c", " a"]
    got = {r.doc_id: r for r in quality_rules.quality_rules(table(spark, rows)).collect()}
    for i, t in enumerate(rows):
        r = got[i]
        assert (r.n_words, r.word_chars, r.n_symbols, r.n_dup_lines, r.n_repeat_words) == _rules_by_hand(t), t
        assert r.base_failed == (r.n_words < 50 or 2 * r.n_repeat_words > r.n_words) and not (r.kept and r.base_failed)
    assert {r.doc_id for r in quality_rules.passing(table(spark, rows)).collect()} == {i for i, r in got.items() if r.kept}
    assert "Python" not in quality_rules.quality_rules(table(spark, rows))._jdf.queryExecution().executedPlan().toString()


def test_language_id(spark):
    rng = random.Random(1)
    parts = {"xx": "ba be bi bo".split(), "yy": "ke ku ka ko".split()}
    rows = [(i, "".join(rng.choices(parts[x], k=rng.randint(5, 40))) + " " + " ".join(rng.choices(parts[x], k=20)), x) for i in range(300) for x in [rng.choice(["xx", "yy"])]]
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string").withColumn("score", F.lit("x"))
    held = F.pmod(F.crc32(F.col("doc_id").cast("string")), F.lit(4)) == 2
    model = language_id.train(docs, ~held)
    got = {r.doc_id: r for r in language_id.identify(docs, model).collect()}
    test = [r.doc_id for r in docs.where(held).collect()]
    assert sum(got[i].lang_pred == rows[i][2] for i in test) / len(test) > 0.98 and all(0 <= r.score <= 1 for r in got.values())
    odd = {r.doc_id: (r.lang_pred, r.score) for r in language_id.identify(table(spark, [None, "", "123 !!", "ba be"]), model).collect()}
    assert odd[0] == odd[1] == odd[2] == ("und", 0.0) and odd[3][0] == "xx"
    none = language_id.train(docs.limit(0))
    assert {r.lang_pred for r in language_id.identify(docs, none).collect()} == {"und"}


def test_language_id_trains_on_whole_texts_and_all_languages(spark, monkeypatch):
    """What tells languages apart may come late in long texts, and a language may be rarer than any bound."""
    kinds = {"xx": "ba be bi bo", "yy": "ke ku ka ko", "zz": "mu my mo mi"}
    rows = [(i, "zo " * 3000 + " ".join([kinds[x]] * 5), x) for i, x in enumerate(["xx"] * 20 + ["yy"] * 12 + ["zz"] * 3)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string")
    got = {r.doc_id: r.lang_pred for r in language_id.identify(docs, language_id.train(docs)).collect()}
    assert got == {i: x for i, _, x in rows}
    monkeypatch.setattr(language_id, "MOST_LANGUAGES", 2)
    few = language_id.train(docs)
    assert few.languages == ["xx", "yy", "zz"]
    assert {r.lang_pred for r in language_id.identify(docs.where("lang = 'zz'"), few).collect()} == {"zz"}


def test_language_kernel_is_the_presence_kernel():
    a, b = "abcab", "abd"
    (_, _, (x, y)), *_ = language_id.grams(pa.array([a, b]))
    grams = lambda t: {t[i : i + n] for n in language_id.LENGTHS for i in range(len(t) - n + 1)}
    assert len(x) == len(grams(a)) and len(y) == len(grams(b)) and len(set(x) & set(y)) == len(grams(a) & grams(b))


def test_language_model_equals_explicit_kernel_regression():
    """The folded weights against Nyström features of a kernel computed from sets of n-grams, solved by least squares."""
    rng = random.Random(9)
    kinds = {"xx": "abcd", "yy": "efgh", "zz": "aeib"}
    names = [rng.choice(list(kinds)) for _ in range(60)]
    texts = [" ".join("".join(rng.choices(kinds[x], k=4)) for _ in range(6)) for x in names]
    ((_, _, present),) = language_id.grams(pa.array(texts))
    model = language_id.fit(present[:40], names[:40])
    sets = [set(p.tolist()) for p in present]
    kernel = lambda a, b: len(a & b) / (len(a) * len(b)) ** 0.5
    marks = [i for x in sorted(set(names[:40])) for i in range(40) if names[i] == x][: 3 * language_id.LANDMARKS_PER_LANGUAGE]
    base = np.array([[kernel(sets[a], sets[b]) for b in marks] for a in marks])
    values, vectors = np.linalg.eigh(base)
    good = values > values.max() * 1e-6
    features = np.array([[kernel(sets[i], sets[b]) for b in marks] for i in range(60)]) @ vectors[:, good] / np.sqrt(values[good])
    features = np.hstack([features, np.ones((60, 1))])
    weight = np.array([40 / names[:40].count(x) for x in names[:40]])
    for c, x in enumerate(model.languages):
        y = np.array([1.0 if n == x else -1.0 for n in names[:40]])
        ridge = np.sqrt(language_id.RIDGE * weight.sum()) * np.eye(features.shape[1])
        left = np.vstack([features[:40] * np.sqrt(weight)[:, None], ridge])
        w, *_ = np.linalg.lstsq(left, np.concatenate([y * np.sqrt(weight), np.zeros(len(ridge))]), rcond=None)
        assert np.allclose(language_id.scores(present, model)[:, c], features @ w, atol=2e-3)


def test_near_duplicates(spark, texts):
    rng = random.Random(3)
    group = []
    for i in range(60):
        w = words(90, 50).split()
        for _ in range(rng.randint(0, 4)):
            w[rng.randrange(len(w))] = f"z{rng.randrange(99)}"
        group.append(" ".join(w))
    rows = texts + group
    sets = {}
    for i, t in enumerate(rows):
        w = (t or "").encode().lower().split()
        sets[i] = {tuple(w[j : j + 4]) for j in range(len(w) - 3)} or ({tuple(w)} if w else set())
    parent = {i: i for i in sets}

    def top(x):
        while parent[x] != x:
            x = parent[x]
        return x

    for i in sets:
        for j in range(i):
            both = len(sets[i] & sets[j])
            if sets[i] and sets[j] and 100 * both >= 80 * (len(sets[i]) + len(sets[j]) - both):
                a, b = top(i), top(j)
                parent[max(a, b)] = min(a, b)
    got = {r.doc_id: (r.n_shingles, r.component_id, r.kept) for r in near_dedup.near_duplicates(table(spark, rows)).collect()}
    assert got == {i: (len(sets[i]), top(i), top(i) == i) for i in sets}
    twice = near_dedup.near_duplicates(table(spark, ["a b c d e", "a b c d e"]).union(table(spark, ["a b c d e"])))
    assert sorted((r.doc_id, r.component_id) for r in twice.collect()) == [(0, 0), (0, 0), (1, 0)]
    kept = near_dedup.without_near_duplicates(table(spark, rows))
    assert kept.columns == table(spark, rows).columns and near_dedup.near_duplicates(table(spark, rows).limit(0)).count() == 0


def test_circulant_signatures_estimate_similarity():
    a, b = np.arange(1, 801, dtype=np.uint64), np.arange(101, 901, dtype=np.uint64)
    s = near_dedup.circulant_signatures(np.concatenate([a, b]), np.array([0, 800, 1600]), 400)
    assert abs((s[0] == s[1]).mean() - 700 / 900) < 0.08
    assert (1 - 0.8**near_dedup.ROWS) ** near_dedup.BANDS < 1e-4


def test_blocks_find_the_links_that_pairs_find(spark):
    sets = spark.createDataFrame([(i, list(range(87 - i))) for i in range(30)], "id long, elements array<long>")
    side = lambda ids: spark.createDataFrame([(i, 87 - i, 0) for i in ids], "id long, n long, main long")
    got = {tuple(r) for r in near_dedup._block_links(side(range(0, 15)), side(range(15, 30)), sets, 80, block=100).collect()}
    assert got == {(a, b) for a in range(15, 30) for b in range(15) if 100 * (87 - a) >= 80 * (87 - b)}


def test_bucket_pairs_in_blocks(spark):
    """Each pair of rows of a bucket in different components once, whatever the number of blocks."""
    rows = spark.createDataFrame([(b, 7, i, i % 5) for b in range(2) for i in range(40) if b == 0 or i < 10], "band int, key long, id long, component long")
    info = spark.createDataFrame([(i, 10, 0, 0, 0, 0) for i in range(40)], "id long, n long, s0 long, s1 long, s2 long, s3 long")
    want = {(a, b) for b in range(40) for a in range(b) if a % 5 != b % 5}
    for block in (3, 100):
        got = [tuple(r) for r in near_dedup._bucket_pairs(rows, info, "true", block).collect()]
        assert len(got) == len(set(got)) and set(got) == want


def test_near_duplicates_chain_in_one_bucket(spark):
    """Texts that are linked only with the next one, all in one bucket: each link counts, whichever row the bucket compares first."""
    names = [f"c{i}" for i in range(40)]
    _, _, values, rows = next(near_dedup._sets(pa.array(names), 1))
    shared = names[int(near_dedup.circulant_signatures(values, rows, 1)[:, 0].argmin())]
    rest = [x for x in names if x != shared]
    chain = table(spark, [" ".join([shared, *rest[i : i + 9]]) for i in range(9)])
    got = near_dedup.near_duplicates(chain, shingle=1, bands=1, per_band=1).collect()
    assert {r.component_id for r in got} == {0} and len(got) == 9


def test_near_duplicates_without_or_with_repeated_ids(spark):
    """Rows are compared by their own texts, whatever ids they lack or share."""
    a, b, c, d = words(60, 1), words(60, 2), words(60, 3), words(60, 4)
    rows = [(1, a), (2, b), (2, a), (None, c), (None, c), (5, d), (None, d), (7, ""), (7, None), (9, b), (9, b), (1, a)]
    docs = spark.createDataFrame(rows, "doc_id long, text string").withColumn("t1", F.lit("x"))
    got = sorted(((r.doc_id, r.component_id) for r in near_dedup.near_duplicates(docs).collect()), key=str)
    assert got == sorted([(1, 1), (2, 2), (2, 1), (None, None), (None, None), (5, 5), (None, 5), (7, 7), (7, 7), (9, 2), (9, 2), (1, 1)], key=str)
    kept = sorted(((r.doc_id, r.text, r.t1) for r in near_dedup.without_near_duplicates(docs).collect()), key=str)
    assert kept == sorted([(1, a, "x"), (2, b, "x"), (None, c, "x"), (5, d, "x"), (7, "", "x"), (7, None, "x")], key=str)
    named = docs.withColumn("doc_id", F.concat(F.lit("d"), "doc_id"))
    assert near_dedup.without_near_duplicates(named).count() == 6


def test_sharding(spark, texts, tmp_path):
    docs = table(spark, texts).repartition(6)
    store = compaction.ShardStore(spark, str(tmp_path / "store"), target_bytes=100_000)
    assert store.read() is None and store.compact() == 0
    first = store.append(docs)
    second = store.append(table(spark, ["late"]))
    merged = store.compact()
    assert (first, second, merged) == (1, 2, 3) and store.compact() == 3
    assert store.manifest().count() < store.manifest(second).count()
    rows = lambda df: sorted(map(str, (tuple(r) for r in df.select(*docs.columns).collect())))
    assert rows(store.read()) == rows(docs.union(table(spark, ["late"]))) == rows(store.read(second)) and rows(store.read(1)) == rows(docs)
    with pytest.raises(compaction.CommitConflict):
        store._commit(store.manifest(), 2)
    assert store.vacuum() > 0 and rows(store.read()) == rows(docs.union(table(spark, ["late"])))
    assert rows(compaction.sharded(docs, str(tmp_path / "one"))) == rows(docs)
    assert rows(compaction.sharded(docs, str(tmp_path / "few"), arrivals=7)) == rows(docs) and compaction.sharded(docs.limit(0), str(tmp_path / "none")).count() == 0


def test_sharding_by_two_writers(spark, texts, tmp_path):
    """A commit in between is built upon, a vacuum leaves files that are being written, and a merge of shards that are gone fails whole."""
    docs, late = table(spark, texts).repartition(3), table(spark, ["late"])
    one, two = (compaction.ShardStore(spark, str(tmp_path / "store"), target_bytes=100_000) for _ in range(2))
    rows = lambda df: sorted(map(str, (tuple(r) for r in df.select(*docs.columns).collect())))
    plain = one._commit

    def slow(shards, base):
        """Another writer commits, and vacuums, between this one's files and its commit."""
        one._commit = plain
        two.append(late)
        two.vacuum()
        return plain(shards, base)

    one._commit = slow
    assert one.append(docs) == 2 and rows(one.read()) == rows(docs.union(late)) and one._names("open") == []
    one._commit = slow
    assert one.compact() == 4 and rows(one.read()) == rows(docs.union(late).union(late))

    def raced(shards, base):
        one._commit = plain
        two.compact()
        return plain(shards, base)

    two.append(docs)
    one._commit = raced
    with pytest.raises(compaction.CommitConflict):
        one.compact()
    assert one._names("open") == [] and rows(one.read()) == rows(docs.union(late).union(late).union(docs))
    assert one.vacuum() > 0 and rows(two.read()) == rows(docs.union(late).union(late).union(docs))


def test_sharding_merges_until_nothing_is_small(spark, texts, tmp_path):
    """Shards end at about target size, however many rounds that takes."""
    store = compaction.ShardStore(spark, str(tmp_path / "store"), target_bytes=20_000, fanout=2)
    for k in range(6):
        store.append(table(spark, texts).repartition(4))
    before = store.version()
    while (before := store.version()) != store.compact():
        assert store.manifest().count() < store.manifest(before).count()
    left = store.manifest().where("bytes < 10000").groupBy("tier").count()
    assert left.where("count > 1").isEmpty() and store.read().count() == 6 * len(texts)


def test_quality_classifier(spark):
    rng = random.Random(2)
    good = lambda i: words(rng.randint(20, 200), i)
    bad = lambda i: words(rng.randint(20, 100), i) + " " + " ".join(x + "***" for x in words(60, i + 1).split())
    rows = [(i, (good if i % 3 else bad)(i)) for i in range(300)]
    docs = spark.createDataFrame(rows, "doc_id long, text string").withColumn("predicted", F.lit("x"))
    labels = spark.createDataFrame([(i, int(i % 3 > 0)) for i in range(300)] + [(None, 1), (5, None)], "doc_id long, quality int")
    held = F.pmod(F.crc32(F.col("doc_id").cast("string")), F.lit(5)) == 0
    model = quality_mil.train(docs, labels, ~held)
    got = {r.doc_id: r for r in quality_mil.classify(docs, model).collect()}
    test = [r.doc_id for r in docs.where(held).collect()]
    assert sum(got[i].predicted == int(i % 3 > 0) for i in test) / len(test) > 0.95
    odd = {r.doc_id: r.score for r in quality_mil.classify(table(spark, [None, "", "word", words(5000, 3)]), model).collect()}
    assert all(0 <= s <= 1 for s in odd.values()) and odd[0] == odd[1] == pytest.approx(model.prior)
    alone = {r.doc_id: r.score for r in quality_mil.classify(docs.where("doc_id = 7"), model).collect()}
    assert alone[7] == pytest.approx(got[7].score, abs=1e-5)
    assert quality_mil.classify(docs, quality_mil.train(docs, labels.limit(0))).count() == 300


def test_quality_scores_equal_a_plain_forward_pass():
    """Batched scores, and the gradient of the loss, against loops over passages and finite differences."""
    import math

    texts = [words(n, n, 50) for n in (5, 70, 200, 33)] + [""]
    ((_, _, x, rows),) = quality_mil.passages(pa.array(texts))
    y = np.array([1, 0, 1, 0], np.float32)
    model = quality_mil.fit(x, rows[:5], y)
    got = quality_mil.score(x, rows, model)
    p = {k: v.astype(float).tolist() for k, v in model.params.items()}
    dot = lambda a, m: [sum(a[i] * m[i][j] for i in range(len(a))) for j in range(len(m[0]))]
    for d in range(4):
        hs, es = [], []
        for row in x[rows[d] : rows[d + 1]]:
            z = [max(-8, min(8, (float(v) - float(m)) / float(s))) for v, m, s in zip(row, model.mean, model.scale, strict=True)]
            h = [math.tanh(a + b) for a, b in zip(dot(z, p["encode"]), p["shift"], strict=True)]
            gate = [math.tanh(a) / (1 + math.exp(-b)) for a, b in zip(dot(h, p["v"]), dot(h, p["u"]), strict=True)]
            hs.append(h)
            es.append(sum(a * b for a, b in zip(gate, p["w"], strict=True)))
        share = [math.exp(e - max(es)) for e in es]
        pooled = [sum(a * h[j] for a, h in zip(share, hs, strict=True)) / sum(share) for j in range(len(hs[0]))]
        assert got[d] == pytest.approx(1 / (1 + math.exp(-sum(a * b for a, b in zip(pooled, p["out"], strict=True)) - p["bias"][0])), abs=1e-4)
    assert got[4] == pytest.approx(0.5) and (np.abs(got[:4] - y) < 0.5).all()


def test_quality_labels_that_disagree_are_left_out(spark):
    docs = spark.createDataFrame([(i, words(40, i)) for i in range(40)], "doc_id long, text string")
    labels = spark.createDataFrame([(i, i % 2) for i in range(39)] + [(3, 0), (4, 0)], "doc_id long, quality int")
    model = quality_mil.train(docs, labels)
    assert model.prior == pytest.approx(18 / 38)


def test_quality_classifier_trains_on_whole_texts(spark):
    """The passages that a model is fitted on are all those of the texts, however long."""
    texts = [words(5000, i, 4000) + (" " + " ".join(x + "***" for x in words(90, i + 1).split()) if i % 2 else "") for i in range(8)] + ["short one", "", None]
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    labels = spark.createDataFrame([(i, 1 - i % 2) for i in range(len(texts))], "doc_id long, quality int")
    model = quality_mil.train(docs, labels)
    x = np.concatenate([x for _, _, x, _ in quality_mil.passages(pa.array(texts, pa.string()))])
    assert len(x) == sum(-(-len((t or "").split()) // quality_mil.PASSAGE_WORDS) for t in texts)
    assert np.allclose(model.mean, x.mean(axis=0), atol=1e-5) and np.allclose(model.scale, x.std(axis=0) + 0.02, atol=1e-5)


def test_hash_columns_are_of_known_form(spark):
    r = decontaminate.contamination(table(spark, ["nothing"]), spark.createDataFrame([(1, "other words")], "item_id long, text string")).first()
    assert r.items_sha256 == hashlib.sha256(b"").hexdigest()
