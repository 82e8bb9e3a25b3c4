"""Attach modes, learners, evaluation and tuning."""
