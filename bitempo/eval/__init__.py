"""Tasks, scores, bootstrap, mutations and the experiment harness."""
