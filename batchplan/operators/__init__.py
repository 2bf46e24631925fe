"""Relational operators of batch scheduling: statistics, overlaps, gains, masks, schedules, measures."""
