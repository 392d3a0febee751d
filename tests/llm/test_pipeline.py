"""The pipeline's stages against brute force on a small table, and on an empty one."""

import os
import re
import sys
import zlib
from collections import Counter, defaultdict

import numpy as np
import pytest

sys.path.insert(0, os.path.dirname(__file__))
from test_operators import brute_links

import corpus_pipeline as P
from clipforge.llm import common, source_mix, token_codes, toxicity
from clipforge.llm.leak_windows import edit_distance, plain

SF = "/root/testdata/sf0.001"
COLUMNS = ["doc_id", "text", "lang", "source", "n_chars"]


@pytest.fixture(scope="module")
def stages(spark):
    """The rows before the first stage and after each."""
    docs = common.table(spark, SF, "documents")
    out = [docs.collect()]
    for name, f in P.STAGES:
        docs = common.materialize(f(spark, docs, SF), name)
        out.append(docs.collect())
        assert name == P.STAGES[-1][0] or docs.columns == COLUMNS
    return out


def ids(rows):
    return Counter(r["doc_id"] for r in rows)


def test_names():
    assert [n for n, _ in P.STAGES] == ["toxicity", "near_duplicates", "decontamination", "mix", "token_codes"]


def test_toxic_documents_go(spark, stages):
    score = toxicity.Scorer(toxicity.train(common.table(spark, SF, "documents"), common.table(spark, SF, "labels")))
    assert ids(stages[1]) == Counter(r["doc_id"] for r in stages[0] if score(r["text"]) < toxicity.THRESHOLD)


def test_one_of_each_class_stays(stages):
    rows = [(r["doc_id"], r["text"], r["source"]) for r in stages[1]]
    assert ids(stages[2]) == Counter({c for _, c, _ in brute_links(rows)})


def test_leaks_go(spark, stages):
    items = [plain(r["text"]) for r in common.table(spark, SF, "benchmark").collect()]
    held = [r["doc_id"] for r in stages[2] if any(i in plain(r["text"]) for i in items)]
    gone = ids(stages[2]) - ids(stages[3])
    assert set(held) <= set(gone)
    texts = {r["doc_id"]: plain(r["text"]) for r in stages[2]}
    assert all(min(edit_distance(i, texts[d])[0] / len(i) for i in items) <= 0.2 for d in gone)


def test_mix_brings_sources_to_their_targets(stages):
    size = {r["doc_id"]: len(re.findall(source_mix.WORD, r["text"])) for r in stages[3]}
    whole, taken = defaultdict(int), defaultdict(int)
    for r in stages[3]:
        whole[r["source"]] += size[r["doc_id"]]
    for r in stages[4]:
        taken[r["source"]] += size[r["doc_id"]]
    targets = source_mix.fill_targets(dict(whole), source_mix.cycle_weights(list(whole)))
    assert max(ids(stages[4]).values()) <= 3 and set(ids(stages[4])) <= set(size)
    left = {s: targets[s] - taken[s] for s in whole}
    assert all(abs(left[s]) <= max(size[r["doc_id"]] for r in stages[3] if r["source"] == s) for s in whole)


def test_codes_hold_what_the_mix_took(stages):
    from tokenizers import Tokenizer

    lib = Tokenizer.from_file(token_codes.default_tokenizer())
    want = []
    for r in stages[4]:
        raw = np.array([*lib.encode(r["text"], add_special_tokens=False).ids, 2], "<u4")
        want.append((r["doc_id"], len(raw), zlib.crc32(raw.tobytes())))
    got = sorted(stages[5], key=lambda r: r["start"])
    assert Counter(want) == Counter((r["doc_id"], r["n_tokens"], r["ids_crc32"]) for r in got)
    assert [r["doc_id"] for r in got] == sorted(r["doc_id"] for r in got)
    assert [r["start"] for r in got] == np.concatenate([[0], np.cumsum([r["n_tokens"] for r in got])[:-1]]).tolist()


def test_run_leaves_its_last_table_only(spark, stages):
    import glob

    from clipforge.sources import scratch

    folder = scratch.scratch_path(spark, "x").rsplit("/", 1)[0]
    before = set(glob.glob(f"{folder}/*"))
    out = P.run(spark, SF)
    left = {p.rsplit("/", 1)[1].rsplit("-", 1)[0] for p in set(glob.glob(f"{folder}/*")) - before}
    assert left == {"pipeline-token_codes"} and ids(out.collect()) == ids(stages[5])


def test_columns_with_clashing_names_pass_through(spark, stages):
    from pyspark.sql import functions as F

    own = ["t1", "t2", "k1", "k1_", "s1_", "doc", "same", "row", "row_", "id", "n", "node", "score", "toxicity_score_", "copy", "times", "takes_", "key", "size", "body", "found", "item_id", "likely_", "p_"]
    docs = common.table(spark, SF, "documents")
    odd = docs.withColumns({c: F.lit(7) for c in own}).withColumns({"bag": F.create_map(F.lit("k"), F.col("doc_id")), "list": F.array("source"), "a.b": F.lit(1)})
    for k, (_, f) in enumerate(P.STAGES):
        docs = f(spark, odd, SF)
        if k + 1 < len(P.STAGES):
            assert docs.columns == odd.columns
            odd = common.materialize(docs, f"clash-{k}")
            assert all(r[c] == 7 for r in odd.select(*own).collect() for c in own) and odd.filter("bag['k'] <> doc_id").isEmpty()
        assert k >= 3 or ids(docs.collect()) == ids(stages[k + 1])  # the mix draws by what a row holds


def test_stages_take_odd_rows(spark):
    rows = [(1, None, "en", "a", 0), (2, "", "en", None, 0), (None, "one two", None, "b", 7), (5, "one two", "en", "b", 7), (5, "one two", "en", "b", 7), (6, "x" * 70_000, "en", "a", 70_000), (7, "word " * 30_000, "en", "c", 150_000)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long")
    for k, (_, f) in enumerate(P.STAGES):
        out = f(spark, docs, SF)
        if k + 1 < len(P.STAGES):
            assert out.columns == docs.columns
            docs = common.materialize(out, f"odd-{k}")
    assert out.count() == docs.count()


def test_empty_table(spark):
    docs = common.table(spark, SF, "documents").limit(0)
    for _, f in P.STAGES:
        docs = f(spark, docs, SF)
        assert docs.count() == 0
