"""Training plans, and the published figures that reports are held against."""
