"""Whole flows: collection to synthesis, the experiments, and the registered queries."""
