"""Plans and constants: operating points, stage mixture, the reference score sheet."""
