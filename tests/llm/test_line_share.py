from callweave.llm import linededup
from tests.llm.test_text_operators import docs_of


def test_lines_on_a_few_hundredths_of_all_hosts_go_and_ordinary_ones_stay(spark):
    """Planted on 6.2 to 10 % of the pages of each host; the most frequent ordinary line of a host reaches 4.8 %."""
    rows, planted = [], [31, 40, 43, 50]
    for h, n in enumerate(planted):
        rows += [(1000 * h + i, "\n".join(["shared notice"] * (i < n) + ["and so on"] * (i % 500 >= 476) + [f"body {h} {i}"]), f"host{h}") for i in range(500)]
    out = linededup.drop_boilerplate(docs_of(spark, rows)).collect()
    assert sum(r["n_dropped"] for r in out) == sum(planted)
    assert not any("shared notice" in r["text"] for r in out)
    assert sum("and so on" in r["text"] for r in out) == 24 * len(planted)
