"""Training-data operators: ten corpus operations that stand apart from the provenance engine.

Nothing else in ``derivatrace`` imports this subpackage.
"""
