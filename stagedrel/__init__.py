"""Staged relation reasoning on Spark: selection, prompts, rewards, group updates, schedules and measures."""
