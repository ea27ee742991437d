"""Second-order optimisation with exact or sketched Hessians."""
