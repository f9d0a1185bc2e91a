import corpus_pipeline
from pathsieve.llm import decontaminate, entries, near_dedup, quality_rules
from pathsieve.llm.line_dedup import without_repeated_lines
from pathsieve.llm.sentence_pieces import PieceModel

SF = "/root/testdata/sf0.001"


def test_stages_follow_each_other(spark):
    import public_tokenizers

    docs = spark.read.parquet(f"{SF}/documents.parquet")
    bench = spark.read.parquet(f"{SF}/benchmark.parquet")
    kept = docs.join(quality_rules.quality_rules(docs).where("kept").select("doc_id"), "doc_id", "left_semi").select(*docs.columns)
    lines = without_repeated_lines(kept).where(r"n_removed = 0 OR text RLIKE '[^ \\t-\\r]'").select(*docs.columns)
    groups = near_dedup.near_duplicates(lines, shingle=5)
    alone = lines.join(groups.where("kept").select("doc_id"), "doc_id", "left_semi").select(*docs.columns)
    rows = alone.collect()
    found = decontaminate.brute_force([r.text for r in rows], {r.item_id: r.text for r in bench.collect()})
    want = {r.doc_id for r, f in zip(rows, found, strict=True) if f[1] == 0}
    assert all(r.text.split() for r in rows)
    got = {r.doc_id: r.ids for r in corpus_pipeline.run(spark, SF).collect()}
    assert set(got) == want and len(corpus_pipeline.STAGES) == 5
    model = PieceModel(public_tokenizers.path("piece_bpe_32k.model"))
    import sentencepiece

    sp = sentencepiece.SentencePieceProcessor(model_file=public_tokenizers.path("piece_bpe_32k.model"))
    some = {r.doc_id: r.text for r in rows if r.doc_id in want}
    assert all(got[i] == sp.encode(some[i]) for i in list(some)[:50]) and model.longest > 1


def test_pipeline_against_brute_force(spark, tmp_path):
    """All stages over a small table with nulls, repeated rows and a clashing column, against plain Python."""
    import random
    import re

    import public_tokenizers
    import sentencepiece
    from test_ops import repeated_run_lines

    rng = random.Random(8)
    stop = "the of and to in".split()

    def line(n, seed):
        r = random.Random(seed)
        return " ".join(r.choice(stop) if r.random() < 0.3 else f"w{r.randrange(3000)}" for _ in range(n))

    item = line(14, 7)
    passage = "\n".join(line(20, 900 + j) for j in range(3))
    near = line(120, 50).split()
    texts = [f"{line(70, i)}\n{line(20, 100 + i)}" for i in range(12)] + ["\n".join([line(60, 200 + i), passage, line(60, 300 + i)]) for i in range(3)]
    for i in range(4):
        w = near[:]
        w[3 * i] = f"changed{i}"
        texts.append(" ".join(w))
    texts += [None, "", line(20, 1), "word " * 90, line(80, 400) + " " + item + " " + line(30, 401), texts[0], line(70, 500) + " ### $$$" * 30]
    rows = [(i, t, "en", f"s{rng.randrange(3)}", len(t or ""), "x") for i, t in enumerate(texts)] + [(5, texts[5], "en", "s", 1, "x")]
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long, row_key string")
    docs.write.parquet(f"{tmp_path}/documents.parquet")
    spark.createDataFrame([(1, item), (2, None)], "item_id long, text string").write.parquet(f"{tmp_path}/benchmark.parquet")

    def passes(text):
        w = (text or "").split()
        grams = [tuple(w[i : i + 3]) for i in range(len(w) - 2)]
        covered = {i + j for i, g in enumerate(grams) if grams.count(g) > 1 for j in range(3)}
        lines = [x for x in (text or "").split("\n") if x.split()]
        every = {x for ws in quality_rules.STOP_WORDS.values() for x in ws.split()}
        n = max(len(w), 1)
        value = {
            "n_words": len(w), "mean_word_chars": sum(map(len, w)) / n, "symbol_ratio": len(re.findall(r"[#*$%&|<>]", text or "")) / n, "shout_ratio": (text or "").count("!") / n,
            "stop_ratio": sum(x.lower().rstrip(".,;:!?") in every for x in w) / n, "dup_line_ratio": (len(lines) - len(set(lines))) / max(len(lines), 1),
        }
        fits = all((r.low is None or value[r.metric] >= r.low) and (r.high is None or value[r.metric] <= r.high) for r in quality_rules.RULES)
        return len(w) >= 50 and 2 * len(covered) <= len(w) and fits

    left = sorted({r[:2] for r in rows if passes(r[1])})
    twice = {r[0] for r in rows if [x[0] for x in rows].count(r[0]) > 1 and passes(r[1])}
    gone = repeated_run_lines([t for _, t in left], 50)
    assert gone == repeated_run_lines([t for _, t in left], 25)
    cut = [(i, "\n".join(x for k, x in enumerate(t.split("\n")) if k not in g)) for (i, t), g in zip(left, gone, strict=True)]
    cut = [(i, t) for i, t in cut if t.split()]
    sets = {i: {tuple(t.lower().split()[j : j + 5]) for j in range(len(t.split()) - 4)} for i, t in cut}
    group = {i: i for i in sets}
    for _ in sets:
        for a in sets:
            for b in sets:
                same = len(sets[a] & sets[b])
                if 100 * same >= 80 * (len(sets[a]) + len(sets[b]) - same):
                    group[a] = group[b] = min(group[a], group[b])
    alone = [(i, t) for i, t in cut if group[i] == i]
    clean = {i: t for (i, t), f in zip(alone, decontaminate.brute_force([t for _, t in alone], {1: item}), strict=True) if not f[1]}
    got = corpus_pipeline.run(spark, str(tmp_path)).collect()
    sp = sentencepiece.SentencePieceProcessor(model_file=public_tokenizers.path("piece_bpe_32k.model"))
    assert {r.doc_id: r.ids for r in got} == {i: sp.encode(t) for i, t in clean.items()} and len(got) == len(clean)
    assert twice == {5} and 5 in clean and len(cut) < len(left) and len(alone) < len(cut) and len(clean) < len(alone)


def test_stages_on_empty_tables(spark, tmp_path):
    docs = spark.createDataFrame([], "doc_id long, text string, lang string, n_words int")
    docs.write.parquet(f"{tmp_path}/documents.parquet")
    spark.createDataFrame([], "item_id long, text string").write.parquet(f"{tmp_path}/benchmark.parquet")
    assert corpus_pipeline.run(spark, str(tmp_path)).count() == 0
    for name, stage in corpus_pipeline.STAGES[:-1]:
        assert stage(spark, docs, str(tmp_path)).columns == docs.columns, name


def test_entries_cover_ten_operators():
    names = entries.queries()
    assert [n.split("_")[0] for n in names] == [f"op{i}" for i in range(1, 11)] and set(entries.oracle_sql()) <= set(names)
