"""Rule programs, fixpoints and materialisation."""
