
import pytest



@pytest.fixture(scope="session")
def docs(spark):
    """Few rows with nulls, blanks, repeats and columns that operators use names of."""

    def make(texts, source=None, ids=None):
        rows = [((ids[i] if ids else i), t, (source[i] if source else "s"), i, "x") for i, t in enumerate(texts)]
        return spark.createDataFrame(rows, "doc_id long, text string, source string, size long, component_id string")

    return make
