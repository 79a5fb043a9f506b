"""The stages, each on its predecessor's rows and against a brute-force version."""

from __future__ import annotations

import zlib
from collections import defaultdict

import numpy as np
import public_tokenizers

import corpus_pipeline
from portsweep.llm import tokens
from portsweep.llm.common import materialize

from . import brute

SF = "/root/testdata/sf0.001"


def test_stages(spark):
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    odd = [(9000, None), (9001, ""), (9002, "a b c " * 200), (9003, "One of them. " * 30 + "Mail to odd@corp.example, 42 of them.")]
    docs = docs.unionByName(spark.createDataFrame(odd, "doc_id bigint, text string"), allowMissingColumns=True)
    columns = docs.columns
    want = {r.doc_id: r.text or "" for r in docs.collect()}
    sizes = [len(want)]
    for name, stage in corpus_pipeline.STAGES[:-1]:
        if name == "quality_rules":
            good = brute.kept(want)
            want = {i: t for i, t in want.items() if i in good}
        elif name == "near_duplicates":
            groups = brute.jaccard(want, 5, 80)
            want = {i: t for i, t in want.items() if groups[i][1] == i}
        elif name == "repeated_passages":
            want = {i: t for i, (t, _) in brute.stripped(want).items()}
        else:
            want = brute.sanitised(want)
        docs = materialize(stage(spark, docs, SF), name)
        assert docs.columns == columns, name
        assert {r.doc_id: r.text or "" for r in docs.collect()} == want, name
        sizes.append(len(want))
    assert sizes[0] > sizes[1] > sizes[2] == sizes[3] == sizes[4]
    assert docs.where("n_chars <> length(text)").count() == 0
    lib, seqs, own = tokens.load(public_tokenizers.path("word_bpe_49k.json")), defaultdict(list), defaultdict(list)
    for r in corpus_pipeline.STAGES[-1][1](spark, docs, SF).collect():
        seqs[r.sequence_id].append((r.offset, r.length))
        own[r.doc_id].append(r)
    assert set(own) == set(want)
    for i, t in want.items():
        ids = np.array([*lib.encode(t, add_special_tokens=False).ids, 1], "<u4")
        for k, r in enumerate(sorted(own[i], key=lambda r: r.piece)):
            assert (r.piece, r.start, r.ids_crc32) == (k, 4096 * k, zlib.crc32(ids[4096 * k : 4096 * (k + 1)].tobytes()))
    for s in seqs.values():
        at = 0
        for offset, length in sorted(s):
            assert offset == at
            at += length
        assert at <= 4096
    total = sum(n for s in seqs.values() for _, n in s)
    assert len(seqs) <= 1 + -(-total // 4096)
