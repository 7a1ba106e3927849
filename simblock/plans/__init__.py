"""Physical-plan helpers: materialisation, global ordering, graph components."""
