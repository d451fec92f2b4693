"""Pages with equal links are counted as classes."""

import itertools
import math

from dyntri import queries
from dyntri.operators import exact


def test_classes_count_as_the_graph_written_out(spark):
    sizes = {1: 3, 4: 1, 6: 5, 7: 2}
    links = [(1, 4), (4, 6), (1, 6), (6, 7)]
    members = [(c, i) for c, n in sizes.items() for i in range(n)]
    joined = lambda x, y: x[0] == y[0] or tuple(sorted((x[0], y[0]))) in links
    want = sum(joined(x, y) and joined(y, z) and joined(x, z) for x, y, z in itertools.combinations(members, 3))
    edges = spark.createDataFrame(links, "u long, v long")
    assert exact.exact_global_of_classes(spark.createDataFrame(list(sizes.items()), "node long, n long"), edges).first()[0] == want
    assert exact.exact_global_of_classes(spark.createDataFrame([(c, 1) for c in sizes], "node long, n long"), edges).first()[0] == 1


def test_copies_of_a_page_make_no_pairs(spark, tmp_path):
    n = 30_000  # 450 million pairs before
    html = '<a href="x"></a><a href="y"></a>'
    spark.range(n).selectExpr("id AS page_id", "'http://h/' AS url", f"'{html}' AS html").write.parquet(f"{tmp_path}/pages.parquet")
    assert queries.queries()["exact_global_page_overlap"](spark, str(tmp_path)).first()[0] == math.comb(n, 3)
