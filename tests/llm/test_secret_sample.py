"""Keys that no pattern covers, in the sample that the models are fitted on."""

import string

import numpy as np
import pytest

from seqstat.llm import secret_scan

SF = "/root/testdata/sf0.001"


def keys(rng, n, alphabet, length=40):
    return ["".join(rng.choice(list(alphabet), length)) for _ in range(n)]


@pytest.mark.parametrize("planted", [0, 5, 50])
def test_unlabelled_keys_in_the_sample(spark, planted):
    rng = np.random.default_rng(3)
    texts = [r["text"] for r in spark.read.parquet(f"{SF}/documents.parquet").select("text").orderBy("doc_id").collect()]
    alphabets = (string.ascii_letters + string.digits, secret_scan.ALPHABET[:64])
    for i, k in enumerate(k for a in alphabets for k in keys(rng, planted, a)):
        texts[i] += f" {k}"
    model = secret_scan.train(texts)
    for a in alphabets:
        assert sum(model.score(k) > model.threshold for k in keys(rng, 200, a)) >= 195
    for w in ("getNextElementOfTheList", "internationalization", "XMLHttpRequestEventTarget", "=" * 40):
        assert model.score(w) <= model.threshold
