"""The positive-unlabelled risk, its slope and the estimated class prior."""

import numpy as np
import pytest

from privbatch.llm import pu_quality


@pytest.mark.parametrize("shift", [0.0, 4.0])
def test_risk_and_slope(shift):
    """Against the risk written out and its slope by differences, on both sides of zero of the bracket."""
    rng = np.random.default_rng(1)
    zp, zu, prior = rng.normal(size=7) + shift, rng.normal(size=9) - shift, 0.6
    loss = lambda z: np.log1p(np.exp(-z))

    def parts(zp, zu):
        return prior * loss(zp).mean(), loss(-zu).mean() - prior * loss(-zp).mean()

    own, rest = parts(zp, zu)
    risk, slope = pu_quality.risk_slope(zp, zu, prior)
    assert (rest < 0) == (shift > 0) and risk == pytest.approx(own + max(0.0, rest))
    step = 1e-6
    for i in range(16):
        d = np.zeros(16)
        d[i] = step
        up, down = parts(zp + d[:7], zu + d[7:]), parts(zp - d[:7], zu - d[7:])
        want = (-(up[1] - down[1]) if rest < 0 else sum(up) - sum(down)) / (2 * step)
        assert slope[i] == pytest.approx(want, abs=1e-6)


@pytest.mark.parametrize("prior", [0.3, 0.8])
def test_class_prior(prior):
    """From positives and a mixture, without a label of the mixture."""
    rng = np.random.default_rng(2)
    good = rng.normal(0.0, 0.1, (6000, pu_quality.WIDTH)).astype(np.float32)
    n = int(3000 * prior)
    mixed = np.concatenate([good[3000 : 3000 + n], rng.normal(0.05, 0.1, (3000 - n, pu_quality.WIDTH)).astype(np.float32)])
    assert pu_quality.class_prior(good[:3000], rng.permutation(mixed)) == pytest.approx(prior, abs=0.06)


def test_labels_other_than_one_are_not_read(spark):
    """Dropping every label 0 changes nothing; a table without documents or labels gives a defined result."""
    docs = spark.createDataFrame([(i, ("good words here " if i % 3 else "### $$$ ") * (3 + i % 5)) for i in range(90)], "doc_id long, text string")
    labels = spark.createDataFrame([(i, int(i % 3 > 0)) for i in range(90)], "doc_id long, quality int")
    one, two = ({r["doc_id"]: r["score"] for r in pu_quality.digest(docs, x).collect()} for x in (labels, labels.where("quality = 1")))
    assert one == two and len(one) == 90
    assert pu_quality.digest(docs.limit(0), labels).count() == 0
    assert {r["score"] for r in pu_quality.digest(docs, labels.limit(0)).collect()} == {0.5}
