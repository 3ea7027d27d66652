"""Rankers, the ranking kernel and the algorithms that combine small rankings."""
