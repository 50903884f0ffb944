"""Node classifiers that give verdicts."""
