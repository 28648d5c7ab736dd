"""Operations of a training-data pipeline: ten operators beside the caption-curation engine.

Nothing else in the library imports this subpackage; `queries` and `oracle_sql` are read by
__spark_entry__.py where the subpackage is present.
"""
