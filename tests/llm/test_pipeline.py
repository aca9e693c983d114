"""run() against a plain version of its stages, and the guard of the entry module."""

import random
import subprocess
import sys
import zlib

import numpy as np
import public_tokenizers
import pytest
from tokenizers import Tokenizer

import corpus_pipeline
from evsketch.llm import packing, pii, quality


def corpus():
    rng = random.Random(7)
    words = ["".join(rng.choice("abcdefghiklmnoprst") for _ in range(rng.randint(2, 8))) for _ in range(300)]
    text = lambda n: " ".join(rng.choice(words) for _ in range(n)) + "."
    shared = text(25)
    rows = [(i, text(rng.randint(20, 90))) for i in range(40)]
    rows += [(50 + i, f"{text(30)} {shared} {text(30)}") for i in range(5)]
    rows += [(60, rows[3][1]), (61, rows[3][1].upper()), (62, rows[5][1] + " more"), (70, "too short"), (71, None), (72, ""), (73, "# $ " * 30)]
    rows += [(80, text(20) + " mail bob@example.org or +1 (706) 555-3138 " + text(20)), (81, text(3000))]
    return rows


def plain(rows):
    rows = [(i, t) for i, t in rows if quality.judge(quality.BASE + quality.ADDED, quality.Text((t or "").encode()))]
    sets, gone = {}, set()
    for i, t in rows:
        w = t.lower().split()
        sets[i] = {tuple(w[j : j + 5]) for j in range(max(1, len(w) - 4))}
    root = {i: i for i in sets}

    def find(x):
        return x if root[x] == x else find(root[x])

    for a in sets:
        for b in sets:
            if a < b and 100 * len(sets[a] & sets[b]) >= 80 * len(sets[a] | sets[b]):
                x, y = find(a), find(b)
                root[max(x, y)] = min(x, y)
    rows = [(i, t) for i, t in rows if find(i) == i and i not in gone]
    seen, out = set(), []
    for i, t in sorted(rows):
        b = t.encode()
        mask, own = bytearray(len(b)), set()
        for p in range(len(b) - 49):
            if b[p : p + 50] in seen:
                mask[p : p + 50] = b"\1" * 50
            own.add(b[p : p + 50])
        seen |= own
        out.append((i, bytes(x for x, m in zip(b, mask, strict=True) if not m).decode()))
    return [(i, pii.rewrite(t, pii.base_spans(t))) for i, t in out]


@pytest.fixture
def sf_dir(spark, tmp_path):
    rows = [(i, t, "en", "s", None if t is None else len(t), "extra") for i, t in corpus()]
    spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long, row string").repartition(2).write.parquet(f"{tmp_path}/documents.parquet")
    return str(tmp_path)


def test_run_equals_the_plain_version(spark, sf_dir):
    tokenizer = Tokenizer.from_file(public_tokenizers.path("byte_bpe_50k.json"))
    want = []
    for i, t in plain(corpus()):
        ids = tokenizer.encode(t, add_special_tokens=False).ids + [0]
        want += [(i, p, a, n, zlib.crc32(np.array(ids[a : a + n], "<u4").tobytes())) for p, (a, n) in enumerate(packing.piece_bounds(len(ids), 2048))]
    got = corpus_pipeline.run(spark, sf_dir).collect()
    assert sorted((r.doc_id, r.piece, r.start, r.length, r.ids_crc32) for r in got) == sorted(want)


def test_stages_keep_the_columns_and_n_chars(spark, sf_dir):
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    columns = docs.columns
    for _, stage in corpus_pipeline.STAGES[:-1]:
        docs = stage(spark, docs, sf_dir)
        assert docs.columns == columns
    assert docs.where("n_chars <> length(text)").count() == 0
    assert [n for n, _ in corpus_pipeline.STAGES] == ["quality_rules", "near_dedup", "suffix_dedup", "pii", "packing"]


def test_entry_without_the_subpackage(tmp_path):
    import shutil
    from pathlib import Path

    root = Path(corpus_pipeline.__file__).parent
    shutil.copytree(root / "evsketch", tmp_path / "evsketch", ignore=shutil.ignore_patterns("llm", "__pycache__"))
    shutil.copy(root / "__spark_entry__.py", tmp_path)
    code = "import __spark_entry__ as e; q = e.queries(); assert len(q) > 100 and 'pipeline' not in q and not any(n.startswith('op1_') for n in q); e.oracle_sql()"
    subprocess.run([sys.executable, "-c", code], cwd=tmp_path, check=True, env={"PATH": "/usr/bin:/bin", "PYTHONPATH": ""})
