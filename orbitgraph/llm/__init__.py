"""Training-data operators: one module each, general interface; ``queries`` holds the thin registered queries."""
