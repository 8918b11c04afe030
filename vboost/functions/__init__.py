"""Column-level mathematics: objectives, gains, codecs, measures and costs."""
