"""Running counts and scoring on streams."""
