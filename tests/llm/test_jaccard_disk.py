"""What the Jaccard join keeps on disk, against the bytes of the texts."""

import random
from pathlib import Path

from transitlens.llm.jaccard_join import jaccard_components
from transitlens.plans import shared


def test_sketches_take_less_than_the_texts(spark):
    draw = random.Random(8)
    rows = [(i, " ".join("".join(draw.choices("abcdefghij", k=6)) for _ in range(115))) for i in range(400)]
    since = shared.mark()
    assert jaccard_components(spark.createDataFrame(rows, "doc_id long, text string").coalesce(1)).count() == 400
    sketches = [p for p in shared._PATHS[since:] if "/jaccard-sketches-" in p]
    held = sum(f.stat().st_size for p in sketches for f in Path(p.removeprefix("file://")).glob("*.parquet"))
    assert 0 < held < sum(len(t) for _, t in rows)
