"""Dataset operators: snippets, stream order, teachers, students, thresholds, measures, theory, costs."""
