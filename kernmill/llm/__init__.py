"""Training-data operators.

Nothing else in the library imports this subpackage; ``queries`` lists what the
entry module registers from here.
"""
