"""The vocabulary that decides what a triple is."""

from __future__ import annotations

from dataclasses import dataclass


@dataclass(frozen=True)
class Vocabulary:
    """Public RDF, RDFS and OWL terms, and one configurable identity predicate.

    The identity predicate says that two terms denote the same thing.  Users of standard data pass the standard IRI.
    """

    type: str = "rdf:type"
    identity: str = "eq:identical"
    sub_class: str = "rdfs:subClassOf"
    sub_property: str = "rdfs:subPropertyOf"
    domain: str = "rdfs:domain"
    range: str = "rdfs:range"
    equivalent_class: str = "owl:equivalentClass"
    equivalent_property: str = "owl:equivalentProperty"
    inverse: str = "owl:inverseOf"
    on_property: str = "owl:onProperty"
    has_value: str = "owl:hasValue"
    some_values: str = "owl:someValuesFrom"
    all_values: str = "owl:allValuesFrom"
    functional: str = "owl:FunctionalProperty"
    inverse_functional: str = "owl:InverseFunctionalProperty"
    symmetric: str = "owl:SymmetricProperty"
    transitive: str = "owl:TransitiveProperty"
    class_term: str = "owl:Class"
    property_term: str = "owl:Property"

    def schema_predicates(self) -> list[str]:
        """Predicates whose triples are schema."""
        return [
            self.sub_class,
            self.sub_property,
            self.domain,
            self.range,
            self.equivalent_class,
            self.equivalent_property,
            self.inverse,
            self.on_property,
            self.has_value,
            self.some_values,
            self.all_values,
        ]

    def schema_classes(self) -> list[str]:
        """Classes whose membership is schema (traits of properties, declarations)."""
        return [self.functional, self.inverse_functional, self.symmetric, self.transitive, self.class_term, self.property_term]


VOCAB = Vocabulary()
