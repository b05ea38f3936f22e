"""Line dedup of short lines."""

from partgraph.llm import line_dedup as L


def test_short_lines_leave(spark):
    long = "a line of more than thirty code points"
    rows = [(1, f"All rights reserved.\nok\n\n{long}\ncat"), (2, f"All rights reserved!\nok\n\n{long}!?\ncar"), (3, "All rights reserved.\n \nAll rightz reserved!!")]
    got = {r.doc_id: r.text for r in L.filter_lines(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    # "rightz ...!!" is two edits away and its length allows one
    assert got == {1: rows[0][1], 2: "\ncar", 3: " \nAll rightz reserved!!"}
