"""Path algebra operators, automaton baselines and aggregation over paths."""
