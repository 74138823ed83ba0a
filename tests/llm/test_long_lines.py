"""Op 3 where the repeated line is a long one."""

from hopwise.llm import quality_rules


def test_long_lines_are_counted(spark):
    notice = " ".join(f"notice{'abcdefghij'[i % 10]}{'klmnopq'[i % 7]}" for i in range(60))
    own = lambda i: " ".join(f"own{i}x{j}" for j in range(10))
    rows = [(i, f"{notice}\n{own(i)}", "a") for i in range(30)]
    rows += [(100 + i, rows[0][1].replace("own0", "copy"), "b") for i in range(30)]  # copies count once
    got = {r["doc_id"]: r for r in quality_rules.quality_rules(spark.createDataFrame(rows, "doc_id long, text string, source string")).collect()}
    assert all(got[i]["n_removed_words"] == 60 and not got[i]["base_failed"] and not got[i]["kept"] for i in range(30))
    assert all(got[100 + i]["n_removed_words"] == 0 and got[100 + i]["kept"] for i in range(30))
