"""Training-data operators: ten large-corpus text operators and their registered queries."""
