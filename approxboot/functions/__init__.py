"""Random numbers, statistics with mergeable states, and accuracy measures."""
