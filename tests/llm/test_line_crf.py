import itertools
import random

import numpy as np
import pyarrow as pa

from winjoin.llm import line_crf as L


def test_forward_backward_against_enumeration():
    rng = np.random.default_rng(1)
    first = np.array([0, 3, 3, 4, 9])
    unary, table = rng.normal(size=9), rng.normal(size=(2, 2))
    good, pairs, log_z = L._chains(unary, table, first)
    want, want_pairs, want_z = np.zeros(9), np.zeros((2, 2)), 0.0
    for a, b in zip(first[:-1], first[1:]):
        if a == b:
            continue
        total, marg, pr = 0.0, np.zeros(b - a), np.zeros((2, 2))
        for y in itertools.product([0, 1], repeat=b - a):
            w = np.exp(sum(unary[a + i] for i in range(b - a) if y[i]) + sum(table[p, q] for p, q in zip(y, y[1:])))
            total += w
            marg += w * np.array(y)
            for p, q in zip(y, y[1:]):
                pr[p, q] += w
        want[a:b], want_z = marg / total, want_z + np.log(total)
        want_pairs += pr / total
    assert np.allclose(good, want) and np.allclose(pairs, want_pairs) and np.isclose(log_z, want_z)


def corpus(n=300):
    rnd = random.Random(4)
    docs = []
    for i in range(n):
        bad = i % 3 == 0
        lines = []
        for _ in range(rnd.randint(1, 6)):
            w = ["".join(rnd.choice("aeinrst") for _ in range(rnd.randint(2, 8))) for _ in range(rnd.randint(4, 30))]
            if bad and rnd.random() < 0.9:
                w = [x.upper() + "!!" for x in w] if i % 2 else [x + " |" for x in w]
            lines.append(" ".join(w))
        docs.append((i, "\n".join(lines), int(not bad)))
    return docs


def test_held_out_accuracy_and_edges(spark):
    docs = corpus()
    d = spark.createDataFrame([(i, t, None) for i, t, _ in docs] + [(1000, None, 1), (1001, "", 1), (1002, "\n\n", 1), (None, docs[0][1], 1), (0, docs[0][1], None)], "doc_id long, text string, quality_score int")
    lab = spark.createDataFrame([(i, q, 0) for i, _, q in docs] + [(5, docs[5][2], 1), (None, 1, 1), (7, None, 0)], "doc_id long, quality int, toxic int")
    model = L.train(d, lab)
    got = L.quality_scores(d, model, keep=["doc_id"]).collect()
    assert len(got) == len(docs) + 5
    score = {r.doc_id: r.quality_score for r in got}
    assert all(0 <= s <= 1 for s in score.values())
    assert np.mean([(score[i] >= 0.7) == q for i, _, q in docs]) > 0.97
    assert score[1000] == score[1001] == score[1002] < 0.5
    assert score[None] == score[0]


def test_one_class_or_no_labels(spark):
    d = spark.createDataFrame([(1, "a b")], "doc_id long, text string")
    none = spark.createDataFrame([], "doc_id long, quality int")
    one = spark.createDataFrame([(1, 1)], "doc_id long, quality int")
    assert L.quality_scores(d, L.train(d, none)).first().quality_score == 0.5
    assert L.quality_scores(d, L.train(d, one)).first().quality_score == 1.0
    assert L.quality_scores(d.limit(0), L.train(d, one)).collect() == []


def test_score_ignores_batching():
    model = L.fit([(*L.line_features(pa.array([t]))[:2], q) for _, t, q in corpus(60)])
    texts = [t for _, t, _ in corpus(20)]
    together = model.score(pa.array(texts))
    assert np.allclose(together, [model.score(pa.array([t]))[0] for t in texts])


def test_lines_of_long_documents_are_bounded_in_training_only(spark):
    from winjoin.llm.line_crf import _spaced, line_features

    import pyarrow as pa

    texts = pa.array(["\n".join(f"line {i} of a text" for i in range(n)) for n in (10, 1000, 300, 256)])
    feats, size, first = line_features(texts)
    f, s, at = _spaced(feats, size, first, 256, 64)
    assert np.diff(at).tolist()[0] == 10 and np.diff(at)[3] == 256 and all(64 <= k <= 256 for k in np.diff(at)[1:3])
    assert (f[at[1]] == feats[first[1]]).all() and (f[at[2] - 1] == feats[first[2] - 1]).all() and s[:10].tolist() == size[:10].tolist()
