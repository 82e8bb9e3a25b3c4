"""Physical strategies for counting, and cost accounting."""
