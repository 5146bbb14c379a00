"""Part of veilgrid; see README.md."""
