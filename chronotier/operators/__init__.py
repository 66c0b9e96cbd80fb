"""Methods over tables of segments, changes, history and vectors."""
