"""The lexicon looks at every candidate, however many are more frequent."""

import random

from trajdp.llm import toxicity


def test_rare_term_behind_many_common_ones(spark):
    rng = random.Random(1)
    common = " ".join("".join(rng.choices("abcdefghij", k=14)) for _ in range(2500))
    toxic = spark.createDataFrame([(common + (" zzyxword" if i % 2 else ""),) for i in range(40)], "text string")
    clean = spark.createDataFrame([(common,) for _ in range(40)], "text string")
    p = toxicity.ToxicityParams()
    assert len(toxicity.beginnings(common, p.least_letters)) > 20_000
    assert toxicity.learned_terms(toxic, clean, 40, 40, p) == ["zzyxword"]
