"""Sub-word lexicons of the locales that the offline provider knows."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

# Translations of the sub-words that the given tables' names are made of.
ES = {
    "region": "region", "nation": "nacion", "customer": "cliente", "supplier": "proveedor", "part": "pieza", "orders": "pedidos", "lineitem": "renglon",
    "regionkey": "claveregion", "nationkey": "clavenacion", "custkey": "clavecliente", "suppkey": "claveproveedor", "partkey": "clavepieza", "orderkey": "clavepedido",
    "name": "nombre", "acctbal": "saldo", "mktsegment": "segmento", "brand": "marca", "type": "tipo", "size": "medida", "retailprice": "precioventa", "orderstatus": "estadopedido",
    "totalprice": "preciototal", "orderdate": "fechapedido", "orderpriority": "prioridad", "linenumber": "numerolinea", "quantity": "cantidad", "extendedprice": "preciobruto",
    "discount": "descuento", "tax": "impuesto", "returnflag": "devuelto", "linestatus": "estadolinea", "shipdate": "fechaenvio", "events": "eventos", "event": "evento", "id": "ident",
    "ts": "instante", "user": "usuario", "value": "valor", "props": "rasgos", "documents": "documentos", "doc": "documento", "text": "texto", "lang": "lengua", "source": "fuente",
    "n": "n", "chars": "letras", "labels": "etiquetas", "quality": "calidad", "toxic": "toxico", "benchmark": "prueba", "item": "caso", "pages": "paginas", "page": "pagina",
    "url": "enlace", "html": "html", "conversations": "charlas", "conv": "charla", "turn": "turno", "role": "papel", "embeddings": "vectores", "vec": "vector", "embedding": "incrustacion",
    "label": "etiqueta",
}
FR = {
    "region": "région", "nation": "nation", "customer": "client", "supplier": "fournisseur", "part": "pièce", "orders": "commandes", "lineitem": "ligne", "name": "nom", "acctbal": "solde",
    "custkey": "cléclient", "nationkey": "clénation", "regionkey": "clérégion", "orderkey": "clécommande", "totalprice": "prixtotal", "orderdate": "datecommande", "quantity": "quantité",
}


def suffixed(word: str) -> str:
    """The invented locale's form of a sub-word: a suffix that follows the last vowel of the stem."""
    back = next((c for c in reversed(word) if c in "aeiou"), "a") in "aou"
    return word + ("ula" if back else "ile")


def lexicon(locale: str, subwords: list[str] | None = None) -> dict[str, str]:
    """sub-word -> localized form. ``inv`` is the invented suffixing locale, whose lexicon is a rule over ``subwords``."""
    if locale == "inv":
        return {w: suffixed(w) if len(w) > 1 else w for w in (subwords or ES)}
    return {"es": ES, "fr": FR}[locale]


def lexicon_table(spark: SparkSession, locale: str, subwords: list[str] | None = None) -> DataFrame:
    return spark.createDataFrame([(locale, k, v) for k, v in lexicon(locale, subwords).items()], "locale string, subword string, localized string")
