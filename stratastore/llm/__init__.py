"""Operations of a training-data pipeline: ten operators, their queries and oracles.

Nothing outside this subpackage imports it; ``__spark_entry__`` adds its queries when it is there.
"""
