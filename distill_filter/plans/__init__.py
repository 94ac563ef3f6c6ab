"""Plans that combine operators: the distillation loop, whole-corpus filtering, recipes, workloads."""
