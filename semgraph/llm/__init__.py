"""Operations of a training-data pipeline: one module an operator, `registry` lists their queries."""
