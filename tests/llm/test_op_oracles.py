import pytest


@pytest.mark.parametrize("key", ["op8_line_dedup", "op9_mixing", "op10_jaccard_join"])
def test_equals_sql(same, key):
    same(key)


def test_every_operator_has_its_query():
    import __spark_entry__ as entry

    names = entry.queries()
    assert all(any(n.startswith(f"op{k}_") for n in names) for k in range(1, 11)) and "pipeline" in names
