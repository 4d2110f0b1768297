"""Training-data operators: ten of them, each in a module of its own, plus the queries that apply them."""
