"""Operations of a training-data pipeline on the documents, pages and benchmark tables.

Nothing else in the library imports this subpackage. One module per operator; ``queries`` wires them to the
``opN_<name>`` keys, and ``corpus_pipeline.py`` at the repository top chains five of them.
"""
