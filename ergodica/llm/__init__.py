"""Operations of a training-data pipeline: one module per operator, plus the queries built from them.

Nothing outside this subpackage imports it.
"""
