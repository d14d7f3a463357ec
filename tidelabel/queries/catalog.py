"""All queries of the label-cleaning engine, by name, with their DuckDB twins."""

from tidelabel.queries import experiments, scoring, streams, surrounding, training

QUERIES: dict = {}
ORACLES: dict[str, str] = {}
for _part in (scoring, training, surrounding, streams, experiments):
    QUERIES |= _part.QUERIES
    ORACLES |= getattr(_part, "ORACLES", {})


def flagship(spark, sf_dir):
    """Rounds of choosing, cleaning and refreshing on labelled documents."""
    return QUERIES["loop_rounds"](spark, sf_dir)
