"""Near copies at thresholds other than 0.85."""

from reclink.llm import oddsketch


def test_pairs_from_four_fifths_on_are_linked(spark):
    """Of 104 words the last 11 differ (89 of 111 runs, 0.802: one group) or 12 (0.786: two)."""
    rows = []
    for i in range(60):
        text = [f"t{i}w{j}" for j in range(104)]
        for k in (0, 11) if i < 40 else (0, 12):
            rows.append((len(rows), " ".join(text[: 104 - k] + [f"t{i}other{j}" for j in range(k)])))
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    kept = sorted(r["doc_id"] for r in oddsketch.drop_near_copies(docs, 80).collect())
    assert kept == [*range(0, 80, 2), *range(80, 120)]


def test_bands_follow_the_threshold():
    for percent in (40, 60, 80, 85, 90):
        assert (1 - (percent / 100) ** oddsketch.ROWS) ** oddsketch.bands(percent) < 1.4e-5
    assert oddsketch.bands(85) == oddsketch.BANDS
