"""The pipeline stage by stage, each against a plain version of itself on the same input."""

import collections

import numpy as np

import corpus_pipeline
from splitsort.llm import common, language_id, sentencepiece_codec

from test_methods import _near_brute


def plain_targets(sizes):
    weights = dict(zip(sorted((s for s in sizes if s is not None)) + ([None] if None in sizes else []), [5.0, 2.0, 1.0] * len(sizes), strict=False))
    target, free, left = {}, set(sizes), float(sum(sizes.values()))
    while free:
        w = sum(weights[s] for s in free)
        over = {s for s in free if left * weights[s] / w > 3 * sizes[s] + 1e-9}
        if not over:
            return target | {s: left * weights[s] / w for s in free}
        target |= {s: 3.0 * sizes[s] for s in over}
        left -= sum(3 * sizes[s] for s in over)
        free -= over
    return target


def test_stages_against_plain_versions(spark, sf_dir):
    import sentencepiece

    docs = common.table(spark, sf_dir, "documents")
    stages, seen = dict(corpus_pipeline.STAGES), []
    for _, stage in corpus_pipeline.STAGES:
        seen.append(docs)
        docs = common.staged(stage(spark, docs, sf_dir), "stage")
    start, clear, single, far, mixed = ([r.asDict() for r in d.collect()] for d in seen)
    out = [r.asDict() for r in docs.collect()]
    assert len(stages) == 5 and all(list(d[0]) == list(start[0]) for d in (clear, single, far, mixed))

    model = language_id.train(seen[0].where(common.doc_crc(seen[0]["doc_id"]) % 4 != 2))
    keep = lambda p: p[0] != language_id.UNKNOWN and not (p[2] and p[1] < 0.5)
    assert sorted(r["doc_id"] for r in clear) == sorted(r["doc_id"] for r in start if keep(language_id.predict(model, r["text"])))

    last = {}
    for r in clear:
        last[r["text"]] = max(r["doc_id"], last.get(r["text"], -1))
    assert sorted(r["doc_id"] for r in single) == sorted(last.values())

    least = _near_brute({r["doc_id"]: r["text"] for r in single})
    assert sorted(r["doc_id"] for r in far) == sorted(i for i, (_, c) in least.items() if i == c)

    size = {r["doc_id"]: len([w for w in r["text"].split(" ") if w]) if not set("\t\n\x0b\x0c\r") & set(r["text"]) else len(r["text"].split()) for r in far}
    by_source = collections.defaultdict(int)
    for r in far:
        by_source[r["source"]] += size[r["doc_id"]]
    target, taken, copies = plain_targets(dict(by_source)), collections.defaultdict(int), collections.Counter(r["doc_id"] for r in mixed)
    for r in far:
        taken[r["source"]] += size[r["doc_id"]] * copies[r["doc_id"]]
        rate = target[r["source"]] / max(1, by_source[r["source"]])
        assert not size[r["doc_id"]] or np.floor(rate + 1e-9) <= copies[r["doc_id"]] <= np.ceil(rate - 1e-9)
    for s, t in target.items():
        assert abs(taken[s] - t) <= max(size[r["doc_id"]] for r in far if r["source"] == s)

    ref, text = sentencepiece.SentencePieceProcessor(model_file=sentencepiece_codec.MODEL), {r["doc_id"]: r["text"] for r in far}
    assert sorted(r["doc_id"] for r in out) == sorted(copies.elements())
    assert all(r["lossless"] and r["ids"] == ref.encode(text[r["doc_id"]]) and r["n_tokens"] == len(r["ids"]) for r in out)

    whole = corpus_pipeline.run(spark, sf_dir)
    assert sorted(r["doc_id"] for r in whole.select("doc_id").collect()) == sorted(copies.elements())
